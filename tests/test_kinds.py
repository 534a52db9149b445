"""Additive, multiplicative and ordered patterns: the whole workflow against brute force."""

import random
from fractions import Fraction
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from vpatterns.operators import coherence as H
from vpatterns.operators import similarity as S
from vpatterns.plans.kinds import discover_kind

CELLS = "obs long, var int, value long"


def table(seed, low=-2, high=2, n_vars=5, n_obs=18):
    rng = random.Random(seed)
    return {(o, v): rng.randint(low, high) for o in range(n_obs) for v in range(n_vars) if rng.random() < 0.85}


def brute(cells, kind, least):
    rows, out = {}, {}
    for (o, v), x in cells.items():
        rows.setdefault(o, {})[v] = x
    for size in range(2, 6):
        for vs in combinations(range(5), size):
            groups = {}
            for r in rows.values():
                if all(v in r for v in vs) and (kind == "additive" or all(r[v] for v in vs)):
                    key = tuple(r[v] - r[vs[0]] if kind == "additive" else Fraction(r[v], r[vs[0]]) for v in vs)
                    groups[key] = groups.get(key, 0) + 1
            out |= {(vs, k): n for k, n in groups.items() if n >= least}

    def shut(vs, offs, n):
        at = dict(zip(vs, offs))
        for (v2, o2), m in out.items():
            if m == n and len(v2) > len(vs) and set(vs) <= set(v2):
                to = dict(zip(v2, o2))
                if all((to[v] - to[vs[0]] if kind == "additive" else to[v] / to[vs[0]]) == at[v] for v in vs):
                    return False
        return True

    return {(vs, tuple(map(float, offs))): n for (vs, offs), n in out.items() if shut(vs, offs, n)}


@pytest.mark.parametrize("kind, low, high, strategy, cap", [("additive", -1, 2, "similar", 2), ("additive", -1, 2, "random", 3), ("multiplicative", -2, 3, "similar", 3), ("multiplicative", -2, 3, "dissimilar", 2)])
def test_offsets(spark, kind, low, high, strategy, cap):
    cells = table(7, low, high)
    values = spark.createDataFrame([(o, v, x) for (o, v), x in cells.items()], CELLS)
    got = discover_kind(values, 18, 0.15, kind, cap, strategy).collect()
    want = brute(cells, kind, 3)
    assert {(tuple(r["vars"]), tuple(round(x, 9) for x in r["offsets"])): r["support"] for r in got} == {(v, tuple(round(x, 9) for x in o)): n for (v, o), n in want.items()}


@pytest.mark.parametrize("cap", [2, 5])
def test_order(spark, cap):
    from itertools import permutations

    cells = table(9, 0, 6)
    values = spark.createDataFrame([(o, v, x) for (o, v), x in cells.items()], CELLS)
    rows = {}
    for (o, v), x in cells.items():
        rows.setdefault(o, {})[v] = x
    want = {}
    for size in range(2, 6):
        for vs in permutations(range(5), size):
            n = sum(all(v in r for v in vs) and all(r[a] < r[b] for a, b in zip(vs, vs[1:])) for r in rows.values())
            if n >= 3:
                want[vs] = n
    got = {tuple(r["seq"]): r["support"] for r in discover_kind(values, 18, 0.15, "order", cap).collect()}
    assert got == want


def test_empty_cells(spark):
    none = spark.createDataFrame([], CELLS)
    for kind in ("additive", "multiplicative", "order"):
        assert discover_kind(none, 10, 0.1, kind).count() == 0


def test_near_ratios_stay_apart_and_large_values_are_refused(spark):
    rows = [(0, 0, 100001), (0, 1, 100000), (1, 0, 100002), (1, 1, 100001), (2, 0, 200002), (2, 1, 200000)]
    values = spark.createDataFrame(rows, CELLS)
    got = H.pivot_differences(values, "multiplicative").groupBy("d").count().collect()
    assert sorted(r["count"] for r in got) == [1, 2]
    with pytest.raises(Exception, match="2\\*\\*26"):
        H.pivot_differences(spark.createDataFrame([(0, 0, 1 << 27), (0, 1, 3)], CELLS), "multiplicative").collect()


def test_sign_policies(spark):
    rows = [(o, v, x) for o, (a, b) in enumerate([(1, 2), (2, 4), (-1, -2), (-3, -6), (1, 3), (0, 5)]) for v, x in ((0, a), (1, b))]
    values = spark.createDataFrame(rows, CELLS)
    got = {p: S.difference_similarity(values, 6, "multiplicative", p).first() for p in S.SIGNS}
    assert got["all"]["purity"] == pytest.approx(1 / 2)  # ratios 2 and 3
    assert got["positive"]["purity"] == pytest.approx(1 / 2)
    assert got["split"]["purity"] == pytest.approx(2 / 3)  # 2 and 3 of positive, 2 of negative values
    assert got["all"]["concentration"] > got["split"]["concentration"] - 1


def test_pairs_that_never_meet_have_zero(spark):
    values = spark.createDataFrame([(0, 0, 1), (1, 1, 2)], CELLS)
    for sim in (S.difference_similarity(values, 2), S.order_similarity_cells(values, 2)):
        assert [(r["a"], r["b"], r["sim"]) for r in sim.collect()] == [(0, 1, 0.0)]


def test_blocks_equal_expressions(spark, monkeypatch):
    monkeypatch.setattr(S, "BLOCK", 3)
    rng = random.Random(1)
    columns = [f"y{i}" for i in range(7)]
    df = spark.createDataFrame([tuple(rng.choice([None, rng.randint(0, 5) + 0.5]) if i < 2 else float(rng.randint(0, 5)) for i in range(7)) for _ in range(60)], ", ".join(f"{c} double" for c in columns)).repartition(3)
    for f in (S.order_similarity, S.pearson):
        name = "sim" if f is S.order_similarity else "score"
        one, many = ({(r["a"], r["b"]): r[name] for r in f(df, columns, engine=e).collect()} for e in ("expressions", "blocks"))
        assert one.keys() == many.keys() and all(one[k] == pytest.approx(many[k], abs=1e-9) for k in one)


def test_longer_sequences_than_ten(spark):
    rows = [(o, v, v) for o in range(2) for v in range(12)]
    values = spark.createDataFrame(rows, CELLS)
    got = H.prefixspan(values, 2, 2)
    assert got.agg(F.max(F.size("seq"))).first()[0] == 12
