"""ASCII points, with or without a leading id, and edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_points(points: DataFrame, path: str, with_id: bool) -> None:
    xs = sorted((c for c in points.columns if c[:1] == "x" and c[1:].isdigit()), key=lambda c: int(c[1:]))
    columns = (["pid"] if with_id else []) + xs
    points.select(F.concat_ws(" ", *(F.col(c).cast("string") for c in columns)).alias("value")).write.mode("overwrite").text(path)


def read_points(spark: SparkSession, path: str, d: int, with_id: bool) -> tuple[DataFrame, DataFrame]:
    """(pid, x0..; the lines that are no points). Blank lines are neither. Ids are hashes of the line where there are none."""
    lines = spark.read.text(path).select(F.trim("value").alias("line")).filter("line <> ''")
    parts = F.split("line", r"[ \t,;]+")
    first = 1 if with_id else 0
    xs = [F.try_element_at(parts, F.lit(first + j + 1)).try_cast("double").alias(f"x{j}") for j in range(d)]
    pid = F.try_element_at(parts, F.lit(1)).try_cast("long") if with_id else F.xxhash64("line")
    rows = lines.select("line", pid.alias("pid"), *xs, (F.size(parts) == first + d).alias("_n"))
    good = F.col("_n") & F.col("pid").isNotNull()
    for j in range(d):
        good &= F.col(f"x{j}").isNotNull() & ~F.isnan(f"x{j}")
    return rows.filter(good).select("pid", *(f"x{j}" for j in range(d))), rows.filter(~F.coalesce(good, F.lit(False))).select("line")


def read_edges(spark: SparkSession, path: str) -> DataFrame:
    """u, v from lines of two integers; comment lines start with #."""
    lines = spark.read.text(path).select(F.split(F.trim("value"), r"[ \t,]+").alias("p")).filter("not startswith(p[0], '#') and size(p) >= 2")
    return lines.select(F.col("p")[0].try_cast("long").alias("u"), F.col("p")[1].try_cast("long").alias("v")).filter("u is not null and v is not null")


def write_edges(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws("\t", F.col("u").cast("string"), F.col("v").cast("string")).alias("value")).write.mode("overwrite").text(path)


def snapshot(state: DataFrame, folder: str, sweep: int) -> None:
    """A restart point: the state after a sweep."""
    state.write.mode("overwrite").parquet(f"{folder}/sweep={sweep}")


def resume(spark: SparkSession, folder: str) -> tuple[DataFrame, int]:
    """The latest snapshot and its sweep."""
    rows = spark.read.parquet(folder)
    last = rows.agg(F.max("sweep")).first()[0]
    return rows.filter(F.col("sweep") == last).drop("sweep"), int(last)
