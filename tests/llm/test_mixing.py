import random

import duckdb
import pandas as pd  # noqa: F401  used by duckdb for the table
import pytest

from vpatterns.llm import mixing


def docs(make, seed):
    rng = random.Random(seed)
    return make([(" ".join("w" * rng.randint(1, 3) for _ in range(rng.choice([0, 3, 40, 200]))), "en", rng.choice(["a", "b", "b", "b", "c", "d", None])) for _ in range(300)])


@pytest.mark.parametrize("seed", [1, 2])
def test_same_as_sql(make, seed):
    df = docs(make, seed)
    con = duckdb.connect()
    con.register("documents", df.toPandas())
    mine = mixing.plan(df).select("doc_id", "size", "source_size", "target", "taken")
    assert sorted(map(tuple, mine.collect())) == sorted(con.sql(mixing.MIX_SQL).fetchall())


def test_shares_and_limits(make):
    df = docs(make, 3)
    source = {r["doc_id"]: r["source"] for r in df.collect()}
    taken, target, size = {}, {}, {}
    for r in mixing.plan(df).collect():
        s = source[r["doc_id"]]
        taken[s] = taken.get(s, 0) + r["taken"]
        target[s], size[s] = r["target"], r["source_size"]
        assert r["taken"] in (0, r["size"], 2 * r["size"])
    assert sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
    for s in taken:
        assert target[s] <= 2 * size[s] and abs(taken[s] - target[s]) <= 400
    rank = sorted(size, key=lambda s: (s is None, s))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(rank)}
    open_ = [s for s in size if target[s] < 2 * size[s] - 1e-6]
    assert len({round(target[s] / weight[s], 6) for s in open_}) <= 1


def test_rows_come_as_often_as_planned(make):
    df = docs(make, 4)
    want = sum(r["copies"] for r in mixing.plan(df).collect())
    assert mixing.mixed(df).count() == want


def test_no_python_in_the_plan(make):
    plan = mixing.plan(docs(make, 5))._jdf.queryExecution().toString()
    assert not any(w in plan for w in ("Python", "Arrow", "Pandas", "Cartesian"))
