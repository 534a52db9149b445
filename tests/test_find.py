"""Any number of variables: the planner's entry point against brute force; masks refuse what they cannot hold."""

import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vpatterns.operators import clustering as C
from vpatterns.operators import merge as M
from vpatterns.operators import mining, prepare
from vpatterns.plans.find import find, planned
from vpatterns.plans.pipeline import discover
from vpatterns.sources import workloads as WL


def sparse(spark, n_vars, n_obs=60, seed=3):
    rng = random.Random(seed)
    rows = {(o, f"v{(o * 7 + k * k + rng.randrange(2)) % n_vars:03d}") for o in range(n_obs) for k in range(4)}
    rows |= {(o, f"v{v:03d}") for o in range(0, n_obs, 3) for v in (1, n_vars // 2, n_vars - 1)}
    rows |= {(v % n_obs, f"v{v:03d}") for v in range(n_vars)}
    return WL.Matrix(spark.createDataFrame(sorted(rows), "obs long, item string"), n_obs), rows


def closed(rows, least):
    held = {}
    for o, i in rows:
        held.setdefault(o, set()).add(i)
    shut = set()
    todo = {frozenset(x) for x in held.values()}
    while todo:  # closed sets of presence rows are the intersections of rows
        shut |= todo
        todo = {a & b for a in todo for b in shut if a & b} - shut
    return {tuple(sorted(p)): n for p in shut if (n := sum(p <= x for x in held.values())) >= least}


@pytest.mark.parametrize("n_vars", [12, 70, 200])
def test_find_is_brute_force(spark, n_vars):
    m, rows = sparse(spark, n_vars)
    assert planned(m, 4).workflow == ("masks" if n_vars == 12 else "wide")
    least = prepare.cutoff(0.04, m.n_obs)
    got = {tuple(r["items"]): r["support"] for r in find(m, 0.04).collect()}
    assert got == closed(rows, least)


def test_one_item_a_row(spark):
    m = WL.Matrix(spark.createDataFrame([(i, f"v{i:02d}") for i in range(70)], "obs long, item string"), 70)
    got = find(m, 0.005).collect()
    assert len(got) == 70 and {r["support"] for r in got} == {1}


def test_masks_refuse_more_variables_than_they_hold(spark):
    m, _ = sparse(spark, 70)
    variables = prepare.numbered(m.cells.select("item").distinct())
    with pytest.raises(Exception, match="62 variables"):
        discover(m, variables, 0.04)
    with pytest.raises(Exception, match="62 variables"):
        prepare.row_masks(m.cells, variables).collect()


@pytest.mark.parametrize("limit", [0, 10**9])
def test_merges_on_both_sides_of_the_broadcast_limit(spark, monkeypatch, limit):
    m, rows = sparse(spark, 12)
    monkeypatch.setattr(mining, "BROADCAST_CANDIDATES", limit)
    monkeypatch.setattr(M, "BROADCAST_CANDIDATES", limit)
    variables = prepare.numbered(m.cells.select("item").distinct())
    names = [r["item"] for r in variables.orderBy("var_id").collect()]
    want = closed(rows, prepare.cutoff(0.04, m.n_obs))
    for merge in ("sequential", "tree", "membership"):
        d = discover(m, variables, 0.04, 4, "random", merge)
        assert {tuple(names[i] for i in range(12) if r["mask"] >> i & 1): r["support"] for r in d.patterns.collect()} == want, merge


def test_maximal_and_overlap_meet_on_variables(spark):
    p = spark.createDataFrame([(m, 10 - bin(m).count("1")) for m in (1, 3, 7, 8, 10, 16)], "mask long, support long")
    assert {r["mask"] for r in M.maximal(p).collect()} == {7, 10, 16}


def test_thousands_of_variables_are_grouped_quickly():
    import time

    s = np.random.default_rng(0).random((2113, 2113))
    began = time.perf_counter()
    home, log = C.fuse_matrix((s + s.T) / 2, 8)
    assert time.perf_counter() - began < 60
    assert np.bincount(home).max() <= 8 and len(log) == 2113 - len(set(home.tolist()))


def naive(scores, n, cap, linkage, sign):
    groups = [[v] for v in range(n)]
    value = {"average": lambda x: sum(x) / len(x), "single": max, "complete": min}[linkage]
    while True:
        best = None
        for a, b in combinations(range(len(groups)), 2):
            if len(groups[a]) + len(groups[b]) <= cap:
                s = sign * round(value([scores[min(i, j), max(i, j)] for i in groups[a] for j in groups[b]]), 9)
                key = (-s, groups[a][0], groups[b][0])
                best = min(best, (key, a, b)) if best else (key, a, b)
        if best is None:
            return {v: g[0] for g in groups for v in g}
        _, a, b = best
        groups[a] = sorted(groups[a] + groups[b])
        del groups[b]
        groups.sort()


@pytest.mark.parametrize("linkage", C.LINKAGES)
def test_fusing_is_the_naive_rule(linkage):
    rng = random.Random(5)
    for _ in range(40):
        n, cap = rng.randrange(2, 11), rng.randrange(1, 6)
        scores = {(a, b): rng.random() for a in range(n) for b in range(a + 1, n)}
        for direction, sign in (("similar", 1), ("dissimilar", -1)):
            if linkage == "average" or sign == 1:
                assert C.fuse(scores, list(range(n)), cap, linkage, direction)[0] == naive(scores, n, cap, linkage, sign)


def test_distributed_grouping_is_disjoint_capped_and_repeats(spark):
    rng = random.Random(2)
    sim = spark.createDataFrame([(a, b, rng.random()) for a in range(30) for b in range(a + 1, 30)], "a int, b int, sim double")
    variables = spark.createDataFrame([(v,) for v in range(30)], "var_id int")
    runs = [sorted(tuple(r) for r in C.capped_clusters_df(sim, variables, 4).collect()) for _ in range(2)]
    assert runs[0] == runs[1] and [v for v, _ in runs[0]] == list(range(30))
    sizes = {}
    for _, c in runs[0]:
        sizes[c] = sizes.get(c, 0) + 1
    assert max(sizes.values()) <= 4
    # no two groups that would fit together are left over
    assert sum(n <= 2 for n in sizes.values()) <= 1


def test_sample_finds_most_and_nothing_wrong(spark):
    m, _ = sparse(spark, 20, 400)
    sig = prepare.cut(prepare.signatures(m.cells, prepare.numbered(m.cells.select("item").distinct())))
    exact = mining.apriori(sig, prepare.cutoff(0.05, m.n_obs))
    found = mining.sample_mine(sig, 0.5, m.n_obs, 0.05)
    assert found.select("mask", "support").exceptAll(exact.select("mask", "support")).count() == 0
    assert mining.recall(found, exact).first()["recall"] >= 0.9


def test_horizontal_parts_advance_together(spark):
    m, _ = sparse(spark, 12)
    sig = prepare.cut(prepare.signatures(m.cells, prepare.numbered(m.cells.select("item").distinct())))
    want = {tuple(r) for r in mining.apriori(sig, prepare.cutoff(0.04, m.n_obs)).select("mask", "support").collect()}
    assert {tuple(r) for r in mining.mine_horizontal(sig, 3, m.n_obs, 0.04).select("mask", "support").collect()} == want
    assert mining.mine_horizontal(sig.where(F.lit(False)), 3, m.n_obs, 0.04).count() == 0
