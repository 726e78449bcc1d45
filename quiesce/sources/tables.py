"""Point sets (pid, x0..) and graphs (u, v) from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# ---- points

_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")


def _whole(c: Column) -> Column:
    return F.round(c).cast("bigint")


def lineitem_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Integer coordinates, so that sums are exact in any order; c: a start that depends on the key only."""
    rows = table(spark, sf_dir, "lineitem")
    xs = [_whole(F.col("l_quantity")), _whole(F.col("l_extendedprice") / 1000), _whole(F.col("l_discount") * 100), _whole(F.col("l_tax") * 100)]
    pid = F.concat_ws("-", *(F.col(c).cast("string") for c in _KEY))
    return rows.select(pid.alias("pid"), *(x.alias(f"x{j}") for j, x in enumerate(xs)), F.col("l_linenumber").alias("line"), F.col("l_orderkey").alias("key"))


def anchored(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four well separated clusters; every seventh order starts in the wrong one, so that real moves happen."""
    rows = lineitem_exact(spark, sf_dir)
    truth = (F.col("line") % 4).cast("int")
    start = F.when(F.col("key") % 7 == 0, (truth + 1) % 4).otherwise(truth)
    return rows.select("pid", *((F.col(f"x{j}") + 1000 * truth).alias(f"x{j}") for j in range(4)), truth.alias("truth"), start.cast("int").alias("start"))


def lineitem_started(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """lineitem_exact with start = (key + line) mod k."""
    return lineitem_exact(spark, sf_dir).withColumn("start", ((F.col("key") + F.col("line")) % k).cast("int"))


def embeddings(spark: SparkSession, sf_dir: str, d: int, k: int) -> DataFrame:
    """The first d components scaled to integers."""
    rows = table(spark, sf_dir, "embeddings")
    xs = [_whole(F.col("embedding")[j].cast("double") * 1048576).alias(f"x{j}") for j in range(d)]
    return rows.select(F.col("vec_id").alias("pid"), *xs, (F.col("vec_id") % k).cast("int").alias("start"))


def event_users(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    rows = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("pid"))
    kinds = rows.agg(F.count(F.lit(1)).alias("x0"), F.countDistinct("event_type").alias("x1"), F.sum(_whole(F.col("value") * 100)).alias("x2"), F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(0)).cast("bigint").alias("x3"))
    return kinds.withColumn("start", (F.col("pid") % k).cast("int"))


def customer_activity(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    orders = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count(F.lit(1)).alias("n"), F.sum(_whole(F.col("o_totalprice"))).alias("paid"))
    rows = table(spark, sf_dir, "customer").join(orders, "c_custkey", "left")
    return rows.select(
        F.col("c_custkey").alias("pid"), F.coalesce("n", F.lit(0)).cast("bigint").alias("x0"), F.coalesce(F.floor(F.col("paid") / 1000), F.lit(0)).cast("bigint").alias("x1"),
        F.floor(F.col("c_acctbal") / 100).cast("bigint").alias("x2"), (F.col("c_custkey") % k).cast("int").alias("start"),
    )


def document_shape(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    text = F.col("text")
    gone = lambda kept: (F.length(text) - F.length(F.regexp_replace(text, kept, ""))).cast("bigint")
    rows = table(spark, sf_dir, "documents")
    return rows.select(F.col("doc_id").alias("pid"), F.length(text).cast("bigint").alias("x0"), gone(" ").alias("x1"), gone("\n").alias("x2"), gone("[0-9]").alias("x3"), (F.col("doc_id") % k).cast("int").alias("start"))


# ---- graphs


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer to supplier, ids kept apart by parity."""
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 2).alias("u"), (F.col("l_suppkey") * 2 + 1).alias("v")).distinct()


def handover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier to the next supplier of the same part by ship date."""
    w = Window.partitionBy("l_partkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice")
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("u"), F.lead("l_suppkey").over(w).alias("v"))
    return rows.filter("v is not null and u <> v").distinct()


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From the bucket of an event's value to that of the user's next event; self-loops stay."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    bucket = (F.floor("value") % 50).cast("bigint")
    return table(spark, sf_dir, "events").select(bucket.alias("u"), F.lead(bucket).over(w).alias("v")).filter("v is not null").distinct()


def page_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page to link path, by name."""
    links = F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("string").alias("a"), F.explode(links).alias("b")).distinct()


def number_vertices(named: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges u, v; vertices id, name) from edges a, b by name; ids 1..N by order of names, without a global window."""
    from ..operators.programs import number

    names = named.select(F.col("a").alias("name")).union(named.select("b")).distinct()
    numbered = number(names.repartitionByRange("name").sortWithinPartitions("name"), "id")
    vertices = numbered.select((F.col("id") + 1).alias("id"), "name")
    edges = named.join(vertices.toDF("u", "a"), "a").join(vertices.toDF("v", "b"), "b").select("u", "v")
    return edges, vertices


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").alias("id")).union(edges.select("v")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("u").agg(F.count(F.lit(1)).alias("dout"))


def dangling(edges: DataFrame) -> DataFrame:
    """Vertices without out-edges."""
    return vertices_of(edges).join(edges.select(F.col("u").alias("id")), "id", "left_anti")
