"""Workloads of the experiments: presence matrices over the given tables.

Each gives (obs, item) rows without repeats and the number of observations of its base
table, which counts those without any item.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.sources.tables import load

TERMS = 40


@dataclass
class Matrix:
    """Presence cells (obs, item, and w where one obs stands for several) and the number of observations.

    ``rows``, where a workload has them at hand: items (array) of each observation.
    """

    cells: DataFrame
    n_obs: int
    rows: DataFrame | None = None


def order_profile(spark: SparkSession, sf_dir: str) -> Matrix:
    line = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    part, supplier = load(spark, sf_dir, "part").select("p_partkey", "p_brand"), load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    joined = line.join(part, line.l_partkey == part.p_partkey).join(supplier, line.l_suppkey == supplier.s_suppkey)
    pair = F.array(F.concat(F.lit("b:"), "p_brand"), F.concat(F.lit("n:"), F.col("s_nationkey").cast("string")))
    return Matrix(joined.select(F.col("l_orderkey").alias("obs"), F.explode(pair).alias("item")).distinct(), load(spark, sf_dir, "orders").count())


def brands(spark: SparkSession, sf_dir: str) -> Matrix:
    """order x brand only."""
    line, part = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    cells = line.join(part, line.l_partkey == part.p_partkey).select(F.col("l_orderkey").alias("obs"), F.col("p_brand").alias("item")).distinct()
    return Matrix(cells, load(spark, sf_dir, "orders").count())


def document_terms(spark: SparkSession, sf_dir: str, top: int = TERMS) -> Matrix:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    terms = docs.select(F.col("doc_id").alias("obs"), F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0))).alias("item"))
    best = terms.groupBy("item").agg(F.count_distinct("obs").alias("f")).orderBy(F.desc("f"), "item").limit(top)
    return Matrix(terms.join(F.broadcast(best.select("item")), "item", "left_semi").select("obs", "item").distinct(), docs.count())


def line_attributes(spark: SparkSession, sf_dir: str) -> Matrix:
    line = load(spark, sf_dir, "lineitem").withColumn("obs", F.monotonically_increasing_id())
    part = load(spark, sf_dir, "part").select("p_partkey", "p_type")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus")
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    nation = load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    wide = line.join(part, line.l_partkey == part.p_partkey, "left").join(orders, line.l_orderkey == orders.o_orderkey, "left")
    wide = wide.join(customer, F.col("o_custkey") == F.col("c_custkey"), "left").join(nation, F.col("c_nationkey") == F.col("n_nationkey"), "left")
    whole = lambda e: F.floor(e).cast("int").cast("string")
    levels = {
        "rf": F.col("l_returnflag"), "ls": F.col("l_linestatus"), "q": whole((F.col("l_quantity") - 1) / 12.5), "d": whole(F.col("l_discount") * 100 / 4),
        "t": whole(F.col("l_tax") * 100 / 3), "ty": F.col("p_type"), "pr": F.col("o_orderpriority"), "st": F.col("o_orderstatus"), "sg": F.col("c_mktsegment"), "rg": F.col("n_regionkey").cast("string"),
    }
    items = F.array(*[F.concat(F.lit(f"{k}="), v) for k, v in levels.items()])
    cells = wide.select("obs", F.explode(items).alias("item")).where("item is not null")
    return Matrix(cells, load(spark, sf_dir, "lineitem").count(), wide.select(F.array_compact(items).alias("items")))


def user_day_events(spark: SparkSession, sf_dir: str) -> Matrix:
    e = load(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    obs = F.concat_ws("/", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    item = F.concat("event_type", F.lit("@"), F.floor(F.hour("ts") / 6).cast("string"))
    cells = e.select(obs.alias("obs"), item.alias("item")).distinct()
    return Matrix(cells, e.select(obs.alias("obs")).distinct().count())


def user_event_hours(spark: SparkSession, sf_dir: str) -> Matrix:
    e = load(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    item = F.concat("event_type", F.lit("@"), F.floor(F.hour("ts") / 6).cast("string"))
    return Matrix(e.select(F.col("user_id").alias("obs"), item.alias("item")).distinct(), e.select("user_id").distinct().count())


def embedding_bins(spark: SparkSession, sf_dir: str, least: float = 0.1) -> Matrix:
    e = load(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    cell = e.select(F.col("vec_id").alias("obs"), F.posexplode("embedding").alias("i", "v")).where(f"abs(v) > {least}D")
    item = F.concat(F.lit("d"), (F.col("i") + 1).cast("string"), F.when(F.col("v") > 0, "+").otherwise("-"))
    return Matrix(cell.select("obs", item.alias("item")), e.count())


def customer_brand(spark: SparkSession, sf_dir: str) -> Matrix:
    line, part = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = line.join(part, line.l_partkey == part.p_partkey).join(orders, line.l_orderkey == orders.o_orderkey)
    return Matrix(joined.select(F.col("o_custkey").alias("obs"), F.col("p_brand").alias("item")).distinct(), load(spark, sf_dir, "customer").count())


#: Name, function and minimum support of each workload.
WORKLOADS = {
    "w1": (order_profile, 0.001),
    "w2": (document_terms, 0.05),
    "w3": (line_attributes, 0.01),
    "w4": (user_day_events, 0.005),
    "w5": (embedding_bins, 0.01),
    "w6": (customer_brand, 0.05),
    "w7": (user_event_hours, 0.01),
}


def planted_numeric(spark: SparkSession, sf_dir: str, width: float = 0.01) -> DataFrame:
    """obs, var, value (whole numbers): embeddings on a grid with four planted patterns.

    By vec_id % 4: additive on 1-5, multiplicative on 6-10, ordered on 11-15, constant on 16-20.
    """
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obs"), "embedding")
    g = F.transform(F.slice("embedding", 1, 20), lambda v: F.floor(v.cast("double") / F.lit(width)).cast("long"))
    e = e.select("obs", g.alias("g"))
    kind = F.col("obs") % 4
    at = lambda i: F.element_at("g", i)
    ordered = F.array_sort(F.slice("g", 11, 5))
    values = []
    for i in range(1, 21):
        v = at(i)
        if i <= 5:
            v = F.when(kind == 0, at(1) + F.lit((0, 1, 3, -2, 2)[i - 1])).otherwise(v)
        elif i <= 10:
            v = F.when(kind == 1, F.lit((2, 4, 8, 1, 6)[i - 6]) * (F.abs(at(6)) % 7 + 1)).otherwise(v)
        elif i <= 15:
            # a strict order: ties are spread by the place
            v = F.when(kind == 2, F.element_at(ordered, i - 10) * 10 + (i - 10)).otherwise(v * 10)
        else:
            v = F.when(kind == 3, F.lit((7, -3, 0, 12, 5)[i - 16]).cast("long")).otherwise(v)
        values.append(v.cast("long"))
    return e.select("obs", F.posexplode(F.array(*values)).alias("p", "value")).select("obs", (F.col("p") + 1).alias("var"), "value")
