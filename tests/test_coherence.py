"""Coherences on small biclusters with one broken row each; offset and order miners by brute force."""

import random
from itertools import combinations, permutations

from pyspark.sql import functions as F

from vpatterns.operators import coherence as H


def cells(spark, *groups):
    rows = [(b, i, j, float(x)) for b, g in enumerate(groups) for i, r in enumerate(g) for j, x in enumerate(r)]
    return spark.createDataFrame(rows, "bicluster_id int, obs_id long, var_id int, value double")


def holds(df):
    return [r["holds"] for r in df.orderBy("bicluster_id").collect()]


def test_coherences(spark):
    assert holds(H.constant_overall(cells(spark, [(2, 2), (2, 2)], [(2, 2), (2, 3)]))) == [True, False]
    assert holds(H.constant_on_variables(cells(spark, [(1, 5, 2), (1, 5, 2)], [(1, 5, 2), (1, 5, 3)]))) == [True, False]
    assert holds(H.additive(cells(spark, [(1, 5, 2), (4, 8, 5), (0, 4, 1)], [(1, 5, 2), (4, 8, 6), (0, 4, 1)]))) == [True, False]
    assert holds(H.multiplicative(cells(spark, [(1, 5, 2), (2, 10, 4), (4, 20, 8)], [(1, 5, 2), (2, 11, 4), (4, 20, 8)], [(0, 5, 2), (2, 10, 4)]), 1e-9)) == [True, False, False]
    assert holds(H.order_preserving(cells(spark, [(1, 9, 4), (0, 3, 2), (5, 8, 6)], [(1, 9, 4), (3, 0, 2)], [(1, 9, 4), (2, 3, 2)]))) == [True, False, False]
    assert holds(H.order_preserving(cells(spark, [(1, 9, 4), (2, 3, 2)]), strict=False)) == [True]
    assert holds(H.order_preserving(cells(spark, [(1, 9), (2, 10), (3, 11)]), "obs")) == [True]


def values(spark, table):
    return spark.createDataFrame([(i, j, x) for i, r in enumerate(table) for j, x in enumerate(r) if x is not None], "obs long, var int, value long")


def additive(table, least, n):
    out = {}
    for size in range(2, n + 1):
        for vs in combinations(range(n), size):
            seen = {}
            for r in table:
                if all(r[v] is not None for v in vs):
                    k = tuple(r[v] - r[vs[0]] for v in vs)
                    seen[k] = seen.get(k, 0) + 1
            out |= {(vs, k): c for k, c in seen.items() if c >= least}
    return out


def test_offsets_and_their_merge(spark):
    rng = random.Random(5)
    table = [[rng.choice([0, 1, 2, None]) for _ in range(5)] for _ in range(30)]
    want = additive(table, 4, 5)
    v = values(spark, table)
    got = {(tuple(r["vars"]), tuple(map(int, r["offsets"]))): r["support"] for r in H.mine_offsets(v, 4).collect()}
    assert got == want
    sides = [H.offset_rows(v.where(c), H.mine_offsets(v.where(c), 4)) for c in ("var < 3", "var >= 3")]
    rows = H.merge_offset(*sides, 4).groupBy("vars", "offsets").agg(F.count("*").alias("n"))
    merged = {(tuple(r["vars"]), tuple(map(int, r["offsets"]))): r["n"] for r in rows.collect() if r["n"] >= 4}
    assert merged == {k: c for k, c in want.items() if min(k[0]) < 3 <= max(k[0])}
    shut = {tuple(r["vars"]) for r in H.closed_offsets(H.mine_offsets(v, 4)).collect()}
    assert shut <= {k[0] for k in want}


def test_orders(spark):
    rng = random.Random(6)
    table = [[rng.randint(0, 6) for _ in range(4)] for _ in range(25)]
    want = {}
    for size in range(2, 5):
        for s in permutations(range(4), size):
            c = sum(all(r[a] < r[b] for a, b in zip(s, s[1:])) for r in table)
            if c >= 5:
                want[s] = c
    v = values(spark, table)
    got = {tuple(r["seq"]): r["support"] for r in H.mine_order(v, 5).collect()}
    assert got == want
    assert {tuple(r["seq"]): r["support"] for r in H.prefixspan(v, 5, 25).collect()} == want
