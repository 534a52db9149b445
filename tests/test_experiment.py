"""The registered experiment is the whole one; its sizes above the cap tell the strategies apart."""

import inspect

import pytest

from vpatterns.operators import prepare
from vpatterns.plans import experiment as X
from vpatterns.plans.pipeline import discover
from vpatterns.registry import queries
from vpatterns.sources import workloads as WL


def matrix(spark, n_vars=8):
    rows = [(obs, f"v{v}") for obs in range(60) for v in range(n_vars) if (obs * (v + 3) + v * v) % 5 < 2 or (v < 4 and obs % 3 == 0)]
    return WL.Matrix(spark.createDataFrame(rows, "obs long, item string"), 60)


def test_registered_over_all_workloads_sizes_and_draws(spark, monkeypatch):
    asked = []

    def record(*args, **more):
        got = inspect.signature(whole).bind(*args, **more)
        got.apply_defaults()
        a = got.arguments
        asked.append((a["name"], tuple(a["sizes"]), a["runs"], a["min_sup"]))
        rows = [(a["name"], s, r, k, m, 1.0 + (s * r) % 7 + len(k) * r % 3) for s in a["sizes"] for r in range(a["runs"]) for k in ("similar", "dissimilar", "random") for m in ("merge_s", "whole_s", "patterns")]
        return spark.createDataFrame(rows, X.SCHEMA)

    whole = X.run_experiment
    monkeypatch.setattr(X, "run_experiment", record)
    tests = queries()["table3_layout"](spark, "/root/testdata/sf0.001").collect()
    want = [(k, (4, 8, 12, 16, 20), 10, ms) for k, (_, ms) in WL.WORKLOADS.items()]
    assert asked == want
    # ten draws of five sizes, of four where a workload has 20 variables
    assert {(r["dataset"], r["df"]) for r in tests} == {(k, 39 if k in ("w4", "w7") else 49) for k in WL.WORKLOADS}
    counts = queries()["table2_layout"](spark, "/root/testdata/sf0.001").collect()
    assert len(counts) == 5 * len(WL.WORKLOADS)


def test_above_the_cap_strategies_differ_and_agree_on_patterns(spark):
    m = matrix(spark)
    variables = prepare.numbered(m.cells.select("item").distinct()).persist()
    found = {s: discover(m, variables, 0.05, 4, s) for s in ("similar", "dissimilar", "random")}
    parts = {s: frozenset(frozenset(r["v"]) for r in d.assignment.groupBy("cluster_id").agg({"var_id": "collect_set"}).toDF("c", "v").collect()) for s, d in found.items()}
    assert len(set(parts.values())) > 1 and all(len(p) > 1 for p in parts.values())
    sig = prepare.signatures(m.cells, variables)
    rows = [(r["mask"], r["w"]) for r in sig.collect()]
    sup = {p: sum(w for x, w in rows if x & p == p) for p in range(1, 256)}
    least = prepare.cutoff(0.05, 60)
    closed = {(p, s) for p, s in sup.items() if s >= least and not any(sup[p | 1 << i] == s for i in range(8) if not p >> i & 1)}
    for d in found.values():
        assert {(r["mask"], r["support"]) for r in d.patterns.collect()} == closed


@pytest.mark.parametrize("cap, sizes", [(4, (9,)), (5, (6,))])
def test_a_draw_in_one_task_is_the_workflow(spark, cap, sizes):
    m = matrix(spark, 10)
    runs = X.run_experiment("m", m, 0.05, sizes, 2, cap).collect()
    got = {(r["n_vars"], r["run"], r["strategy"], r["metric"]): r["value"] for r in runs}
    for size in sizes:
        for run in (1,):
            variables = prepare.numbered(prepare.draw(m.cells, size, run)).persist()
            for strategy in ("similar", "dissimilar", "random"):
                d = discover(m, variables, 0.05, cap, strategy)
                at = lambda k: got[size, run, strategy, k]
                lengths = [bin(r["mask"]).count("1") for r in d.local.collect()]
                assert at("patterns") == d.patterns.count() and at("local_patterns") == len(lengths)
                assert at("mean_length") == pytest.approx(sum(lengths) / len(lengths))
                assert at("compared") == d.measures["compared"] and at("kept") == d.measures["kept"]
                assert at("extension_rate") == pytest.approx(X.extension_rate(d.local, d.patterns).first()["rate"])


def test_size_twenty_equals_mining_without_groups(spark):
    from vpatterns.operators.closed import closed_patterns

    m = matrix(spark, 20)
    runs = X.run_experiment("m", m, 0.1, (20,), 1).where("metric = 'patterns'").collect()
    assert {r["value"] for r in runs} == {closed_patterns(m, 0.1).count()} and len(runs) == 3


def test_too_large_a_draw_is_refused(spark):
    from vpatterns.plans import draws

    with pytest.raises(ValueError, match="24 variables"):
        draws.measured(None, None, ["v"] * 25, 1, 1, 4)
