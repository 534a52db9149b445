"""Closed patterns over all variables at the stated support, against brute force."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from vpatterns.operators import closed
from vpatterns.operators.closed import closed_patterns
from vpatterns.operators.prepare import cutoff, distinct_rows, numbered
from vpatterns.plans.wide import discover_wide, placed_variables
from vpatterns.registry import queries
from vpatterns.sources import workloads as WL


def brute(rows, n_vars, least):
    sup = {p: sum(x & p == p for x in rows) for p in range(1, 1 << n_vars)}
    return {(tuple(f"v{i:02d}" for i in range(n_vars) if p >> i & 1), s) for p, s in sup.items() if s >= least and not any(sup[p | 1 << i] == s for i in range(n_vars) if not p >> i & 1)}


def as_set(df):
    got = [(tuple(r["items"]), r["support"]) for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


@pytest.mark.parametrize("dense, table", [(0, 0), (26, 18), (26, 6)])
@pytest.mark.parametrize("seed, share, always", [(1, 0.5, False), (2, 0.8, True), (3, 0.2, False)])
def test_brute_force(spark, monkeypatch, seed, share, always, dense, table):
    monkeypatch.setattr(closed, "DENSE", dense)
    monkeypatch.setattr(closed, "TABLE", table)
    rng, n_vars = random.Random(seed), 10
    rows = [sum((rng.random() < share or (always and i == 4)) << i for i in range(n_vars)) for _ in range(50)]
    rows = [x | (x & 1) << 7 for x in rows]  # one variable implies another
    cells = spark.createDataFrame([(o, f"v{i:02d}") for o, x in enumerate(rows) for i in range(n_vars) if x >> i & 1], "obs long, item string")
    assert as_set(closed_patterns(WL.Matrix(cells, 50), 0.04)) == brute(rows, n_vars, cutoff(0.04, 50))


def test_more_variables_than_a_mask_holds(spark):
    m = WL.embedding_bins(spark, "/root/testdata/sf0.001")
    assert as_set(closed_patterns(m, 0.055)) == as_set(discover_wide(m, 0.055))


def test_registered_query_finds_patterns_beyond_the_twelve_most_frequent(spark):
    sf = "/root/testdata/sf0.001"
    m = WL.user_day_events(spark, sf)
    listed = closed_patterns(m, 0.005)
    got = {(frozenset(i), s) for i, s in as_set(listed)}
    single = {frozenset([r["item"]]) for r in m.cells.groupBy("item").count().collect() if r["count"] >= cutoff(0.005, m.n_obs)}
    assert len(single) > 12 and len(set().union(*(p for p, _ in got))) == len(single)
    assert got == {(frozenset(i), s) for i, s in as_set(discover_wide(m, 0.005))}
    of_length = {n: [s for i, s in got if len(i) == n] for n in {len(i) for i, _ in got}}
    whole = {r["n_vars"]: tuple(r)[1:] for r in queries()["w4_whole"](spark, sf).collect()}
    assert whole == {n: (len(s), min(s), max(s), sum(s)) for n, s in of_length.items()}


def test_measures_are_over_all_variables(spark):
    sf = "/root/testdata/sf0.001"
    got = {(r["strategy"], r["metric"]): (r["n_vars"], r["value"]) for r in queries()["w4_whole_measures"](spark, sf).collect()}
    n = WL.user_day_events(spark, sf).cells.select("item").distinct().count()
    assert {k for k, _ in got} == {"similar", "dissimilar", "random"} and {v for v, _ in got.values()} == {n} and n > 12
    assert {v for (_, k), (_, v) in got.items() if k == "patterns"} == {float(closed_patterns(WL.user_day_events(spark, sf), 0.005).count())}


def test_equal_observations_are_one_weighted_row(spark):
    m = WL.line_attributes(spark, "/root/testdata/sf0.001")
    lines = spark.createDataFrame([(i, x) for i in range(40) for x in ("ab", "abc", "c")[i % 3]], "obs long, item string")
    for whole in (m, WL.Matrix(lines, 41)):
        small = distinct_rows(whole)
        n = small.cells.select("obs").distinct().count()
        assert n == whole.cells.groupBy("obs").agg(F.array_sort(F.collect_list("item")).alias("i")).select("i").distinct().count()
        assert small.cells.agg(F.sum("w")).first()[0] == whole.cells.count()
        variables = numbered(whole.cells.select("item").distinct()).persist()
        similar = [sorted(map(tuple, placed_variables(x, variables, 4, "similar").collect())) for x in (whole, small)]
        assert similar[0] == similar[1]
        assert as_set(closed_patterns(small, 0.05)) == as_set(closed_patterns(whole, 0.05))


@pytest.mark.parametrize("table, step, batch", [(3, 2, 5), (13, 8, 48), (1, 4, 3)])
@pytest.mark.parametrize("seed, share, least", [(1, 0.6, 0.02), (2, 0.9, 0.1), (3, 0.97, 0.02)])
def test_dense_matrix_is_counted_without_a_list(spark, monkeypatch, seed, share, least, table, step, batch):
    from vpatterns.operators import tally

    monkeypatch.setattr(closed, "DENSE", 0)
    listed = closed_patterns
    monkeypatch.setattr(closed, "closed_patterns", None)
    for name, value in (("TABLE", table), ("STEP", step), ("BATCH", batch), ("DEAL", 3)):
        monkeypatch.setattr(tally, name, value)
    rng, n_vars = random.Random(seed), 11
    rows = [sum((rng.random() < share) << i for i in range(n_vars)) for _ in range(60)]
    rows = [x | (x & 1) << 7 for x in rows]  # one variable implies another
    cells = spark.createDataFrame([(o, f"v{i:02d}", 1 + o % 3) for o, x in enumerate(rows) for i in range(n_vars) if x >> i & 1], "obs long, item string, w int")
    m = WL.Matrix(cells, 120)
    of_length = {}
    for items, s in as_set(listed(m, least)):
        of_length.setdefault(len(items), []).append(s)
    got = {r["n_vars"]: tuple(r)[1:] for r in closed.closed_by_length(m, least).collect()}
    assert got == {n: (len(s), min(s), max(s), sum(s)) for n, s in of_length.items()}


def test_measures_of_a_dense_matrix_make_no_list(spark, monkeypatch):
    from vpatterns.queries import mine

    rng, n_vars = random.Random(5), 8
    rows = [sum((rng.random() < 0.8) << i for i in range(n_vars)) for _ in range(40)]
    cells = spark.createDataFrame([(o, f"v{i:02d}") for o, x in enumerate(rows) for i in range(n_vars) if x >> i & 1], "obs long, item string")
    m = WL.Matrix(cells, 40)
    monkeypatch.setitem(WL.WORKLOADS, "dense", (lambda *_: m, 0.04))
    monkeypatch.setattr(closed, "DENSE", 4)
    for module in (closed, mine):
        monkeypatch.setattr(module, "closed_patterns", None, raising=False)
    got = {(r["strategy"], r["metric"]): r["value"] for r in mine._whole_measures("dense")(spark, "").collect()}
    assert {got[s, "patterns"] for s in ("similar", "dissimilar", "random")} == {float(len(brute(rows, n_vars, cutoff(0.04, 40))))}


@pytest.mark.parametrize("deal, small, widths, few", [(3, 2, (2, 4, 6), 2), (1, 0, (3, 8, 64), 8), (10, 11, (8, 16, 64), 0)])
@pytest.mark.parametrize("seed, share, least", [(1, 0.6, 0.02), (2, 0.9, 0.1), (3, 0.97, 0.02)])
def test_number_of_closed_patterns_of_a_dense_matrix(spark, monkeypatch, seed, share, least, deal, small, widths, few):
    from vpatterns.operators import number

    monkeypatch.setattr(closed, "DENSE", 0)
    for module, name, value in ((closed, "closed_patterns", None), (closed, "closed_counts", None), (number, "DEAL", deal), (number, "SMALL", small), (number, "WIDTHS", widths), (number, "FEW", few), (number, "BATCH", 3)):
        monkeypatch.setattr(module, name, value)
    rng, n_vars = random.Random(seed), 11
    rows = [sum((rng.random() < share) << i for i in range(n_vars)) for _ in range(60)]
    rows = [x | (x & 1) << 7 for x in rows]  # one variable implies another
    cells = spark.createDataFrame([(o, f"v{i:02d}", 1 + o % 3) for o, x in enumerate(rows) for i in range(n_vars) if x >> i & 1], "obs long, item string, w int")
    weighed = [x for o, x in enumerate(rows) for _ in range(1 + o % 3)]
    assert closed.number_of_closed(WL.Matrix(cells, 120), least) == len(brute(weighed, n_vars, cutoff(least, 120)))


def test_number_goes_with_rows_and_not_with_patterns():
    from vpatterns.operators.number import Number

    # any set of variables may be missing: 2**45 closed patterns
    missing = np.array([0, *(1 << i for i in range(45))], np.int64)
    assert Number(1).count(missing, missing, np.ones(46, np.int64), 0, (1 << 45) - 1) == 1 << 45
    # two of the 40 are missing together only
    missing = np.array([0, 3, *(1 << i for i in range(2, 40))], np.int64)
    assert Number(1).count(missing, missing, np.ones(40, np.int64), 0, (1 << 40) - 1) == 1 << 39
