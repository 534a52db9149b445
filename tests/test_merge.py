"""Merging against brute force on the worked example and on random matrices."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from vpatterns.operators import clustering as C
from vpatterns.operators import merge as M
from vpatterns.operators import mining
from vpatterns.operators import prepare as P
from vpatterns.plans import pipeline as D
from vpatterns.plans.wide import discover_wide
from vpatterns.sources.workloads import Matrix

ROWS = ["ABCE", "ABCEF", "ABDE", "ABCDEF", "CDF", "CD", "ABE", ""]


def matrix(spark, rows):
    return Matrix(spark.createDataFrame([(i, c) for i, r in enumerate(rows) for c in r], "obs long, item string"), len(rows))


def closed(rows, min_sup):
    names = sorted({c for r in rows for c in r})
    cover = {}
    for m in range(1, 1 << len(names)):
        s = {names[i] for i in range(len(names)) if m >> i & 1}
        obs = frozenset(i for i, r in enumerate(rows) if s <= set(r))
        if len(obs) / len(rows) > min_sup:
            cover.setdefault(obs, set()).update(s)
    return {("".join(sorted(s)), len(o)) for o, s in cover.items()}


def named(patterns, names):
    return {("".join(names[i] for i in range(len(names)) if r["mask"] >> i & 1), r["support"]) for r in patterns.collect()}


@pytest.mark.parametrize("merge", ["sequential", "tree", "membership"])
@pytest.mark.parametrize("strategy", D.STRATEGIES)
def test_worked_example(spark, merge, strategy):
    m = matrix(spark, ROWS)
    found = D.discover(m, P.numbered(m.cells.select("item").distinct()), 0.25, 3, strategy, merge)
    assert named(found.patterns, "ABCDEF") == {("C", 5), ("D", 4), ("CD", 3), ("CF", 3), ("ABE", 5), ("ABCE", 3)}


def test_worked_clusters(spark):
    m = matrix(spark, ROWS)
    sig = P.signatures(m.cells, P.numbered(m.cells.select("item").distinct()))
    variables = P.numbered(m.cells.select("item").distinct())
    homes = {s: {r["var_id"]: r["cluster_id"] for r in D.group_variables(sig, variables, 8, 3, s).collect()} for s in ("similar", "dissimilar")}
    assert homes["similar"] == {0: 0, 1: 0, 4: 0, 2: 2, 3: 2, 5: 2}
    assert homes["dissimilar"] == {0: 0, 2: 0, 3: 0, 1: 1, 4: 1, 5: 1}


@pytest.mark.parametrize("seed", range(4))
def test_random_matrices(spark, seed):
    rng = random.Random(seed)
    rows = ["".join(c for c in "ABCDEFG" if rng.random() < 0.55) for _ in range(24)]
    m = matrix(spark, rows)
    found = D.discover(m, P.numbered(m.cells.select("item").distinct()), 0.15, 3, "random", ("sequential", "tree", "membership")[seed % 3])
    assert named(found.patterns, "ABCDEFG") == closed(rows, 0.15)


@pytest.mark.parametrize("strategy", D.STRATEGIES)
def test_wide_worked_example(spark, strategy):
    got = {("".join(r["items"]), r["support"]) for r in discover_wide(matrix(spark, ROWS), 0.25, 3, strategy).collect()}
    assert got == {("C", 5), ("D", 4), ("CD", 3), ("CF", 3), ("ABE", 5), ("ABCE", 3)}


def test_more_variables_than_a_mask_holds(spark):
    rng = random.Random(9)
    rows = ["".join(chr(200 + i) for i in range(70) if rng.random() < 0.12 or (n % 3 == 0 and i in (1, 30, 66))) for n in range(40)]
    got = {("".join(r["items"]), r["support"]) for r in discover_wide(matrix(spark, rows), 0.1, 6, "random").collect()}
    want = set()
    for size in (1, 2, 3, 4):
        for s in combinations([chr(200 + i) for i in range(70)] if size < 3 else sorted({c for p, _ in want for c in p}), size):
            obs = [r for r in rows if set(s) <= set(r)]
            if len(obs) / 40 > 0.1:
                shared = set.intersection(*map(set, obs))
                want.add(("".join(sorted(shared)), len(obs)))
    assert got == want


def test_strict_threshold():
    assert P.cutoff(0.25, 8) == 3
    assert P.cutoff(0.0, 8) == 1
    assert P.cutoff(0.1, 10) == 2
    assert P.cutoff(1.0, 4) == 5


def test_caps():
    s = {(a, b): 1 / (1 + a + b) for a in range(7) for b in range(a + 1, 7)}
    for cap in (1, 2, 3, 7, 9):
        for linkage in C.LINKAGES:
            home, log = C.fuse(s, list(range(7)), cap, linkage)
            sizes = [list(home.values()).count(c) for c in set(home.values())]
            assert max(sizes) <= cap and sum(sizes) == 7 and len(log) == 7 - len(sizes)


def test_distributed_clusters_keep_the_cap(spark):
    rows = [(a, b, ((a * 7 + b * 13) % 10) / 10) for a in range(9) for b in range(a + 1, 9)]
    sim = spark.createDataFrame(rows, "a int, b int, sim double")
    got = C.capped_clusters_df(sim, spark.createDataFrame([(v,) for v in range(9)], "var_id int"), 3).collect()
    homes = [r["cluster_id"] for r in got]
    assert sorted(r["var_id"] for r in got) == list(range(9)) and max(map(homes.count, homes)) <= 3


def test_empty_matrix_and_too_high_threshold(spark):
    m = matrix(spark, ["A", "B"])
    variables = P.numbered(m.cells.select("item").distinct())
    assert D.discover(m, variables, 1.0).patterns.count() == 0
    none = Matrix(m.cells.where("false"), 2)
    assert mining.apriori(P.signatures(none.cells, variables), 1).count() == 0


def test_both_ways_of_counting_support(spark):
    sig = spark.createDataFrame([(0b111, 3), (0b101, 2), (0b010, 4)], "mask long, w long")
    c = spark.createDataFrame([(0b101,), (0b010,)], "mask long")
    near = sorted(map(tuple, mining.support(c, sig, n=2).collect()))
    assert near == sorted(map(tuple, mining.support(c, sig).collect())) == [(0b010, 7), (0b101, 5)]


def test_closed_forms_agree(spark):
    m = matrix(spark, ROWS)
    sig = P.signatures(m.cells, P.numbered(m.cells.select("item").distinct()))
    found = mining.enumerate_patterns(sig, 6, 3)
    assert found.count() == 19
    assert sorted(map(tuple, M.closed_pairwise(found).collect())) == sorted(map(tuple, M.closed_collapse(found, sig).collect()))


def test_no_cartesian_over_rows(spark):
    m = matrix(spark, ROWS)
    plan = P.signatures(m.cells, P.numbered(m.cells.select("item").distinct()))._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "BatchEvalPython" not in plan


def test_scan_is_pruned(spark):
    from vpatterns.sources.tables import load

    df = load(spark, "/root/testdata/sf0.001", "lineitem").where("l_quantity > 45").groupBy("l_returnflag").agg(F.count("*"))
    plan = df._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in plan and "l_extendedprice" not in plan.split("ReadSchema")[-1]
