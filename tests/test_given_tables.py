"""Queries that once made their numbers up: each reads given tables and gives the rows of its SQL."""

import duckdb
import pytest
from pyspark.errors import AnalysisException

from vpatterns.registry import oracle_sql, queries

SF = "/root/testdata/sf0.001"
READERS = {
    "measure_pattern_bound": "events",
    "min_support_table1": "part lineitem orders customer events",
    "min_support_variants": "orders part lineitem",
    "pearson_blind_spot": "embeddings",
    "udf_tails": "customer nation",
}


@pytest.mark.parametrize("name", READERS)
def test_reads_given_tables(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        queries()[name](spark, str(tmp_path)).collect()
    con = duckdb.connect()
    for t in READERS[name].split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df, want = queries()[name](spark, SF), con.sql(oracle_sql()[name])
    at = [want.columns.index(c) for c in df.columns]
    assert sorted(map(tuple, df.collect()), key=repr) == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=repr)
