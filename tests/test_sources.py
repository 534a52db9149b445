import pytest

from vpatterns.sources import tables as T


def test_baskets(spark, tmp_path):
    (tmp_path / "b.txt").write_text("a b b\n\nc\n")
    got = T.read_baskets(spark, f"file://{tmp_path}/b.txt")
    assert sorted(r["item"] for r in got.collect()) == ["a", "b", "c"] and got.select("obs").distinct().count() == 2


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_typed_reads(spark, tmp_path, kind):
    spark.range(3).write.format(kind).save(f"file://{tmp_path}/x")
    assert T.read_typed(spark, f"file://{tmp_path}/x", kind, "id long").count() == 3


def test_writing_a_run_again_replaces_it(spark, tmp_path):
    path = f"file://{tmp_path}/runs"
    for n, run in ((3, "a"), (2, "b"), (5, "a")):
        T.write_run(spark.range(n), path, run)
    got = {r["run_id"]: r["count"] for r in spark.read.parquet(path).groupBy("run_id").count().collect()}
    assert got == {"a": 5, "b": 2}


def test_small_refuses_large(spark):
    assert T.small(spark.range(5), 5).num_rows == 5
    with pytest.raises(ValueError):
        T.small(spark.range(6), 5)
