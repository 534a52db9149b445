"""Every linkage reaches the distributed form of grouping."""

from vpatterns.operators import clustering as C


def test_linkage_above_the_driver_limit(spark, monkeypatch):
    # a chain: single linkage takes 2 to {0, 1}, complete linkage leaves 2 to 3
    s = {(0, 1): 0.9, (1, 2): 0.8, (0, 2): 0.1, (2, 3): 0.5, (1, 3): 0.05, (0, 3): 0.04}
    sim = spark.createDataFrame([(a, b, x) for (a, b), x in s.items()], "a int, b int, sim double")
    monkeypatch.setattr(C, "DRIVER_LIMIT", 3)
    found = {}
    for linkage in ("single", "complete"):
        got = C.capped_clusters(sim, [0, 1, 2, 3], 3, linkage)
        found[linkage] = {r["var_id"]: r["cluster_id"] for r in got.collect()}
        assert found[linkage] == C.fuse(s, [0, 1, 2, 3], 3, linkage)[0]
    assert found["single"] != found["complete"]
