"""Measures of accuracy, work and time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def l1(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: sum and largest of |pr - pr'| over vertices."""
    gap = F.abs(F.coalesce("pr", F.lit(0.0)) - F.coalesce("pr2", F.lit(0.0)))
    return a.select("id", "pr").join(b.select("id", F.col("pr").alias("pr2")), "id", "full").agg(F.sum(gap).alias("l1"), F.max(gap).alias("linf"))


def mass(ranks: DataFrame) -> DataFrame:
    return ranks.agg(F.sum("pr").alias("mass"))


def top_n(ranks: DataFrame, n: int) -> DataFrame:
    """The n largest ranks, ties to the smaller id."""
    return ranks.orderBy(F.desc(F.round("pr", 9)), "id").limit(n)


def topn_overlap(a: DataFrame, b: DataFrame, n: int) -> float:
    return top_n(a, n).join(top_n(b, n).select("id"), "id", "left_semi").count() / n


def kendall(a: DataFrame, b: DataFrame, limit: int = 2000) -> float:
    """Share of agreeing pairs less that of disagreeing ones, over the ``limit`` common vertices that rank highest in ``a``: a measure of the top, not of all."""
    x = a.join(b.select("id", F.col("pr").alias("pr2")), "id").orderBy(F.desc("pr"), "id").limit(limit).select("pr", "pr2").toPandas().to_numpy()
    if len(x) < 2:
        return 1.0
    import numpy as np

    s = np.sign(x[:, None, 0] - x[None, :, 0]) * np.sign(x[:, None, 1] - x[None, :, 1])
    return float(s.sum() / (len(x) * (len(x) - 1)))


def speedup(times: DataFrame, baseline: str) -> DataFrame:
    """times(variant, size, secs): adds the baseline's time at the same size over the variant's."""
    base = times.filter(F.col("variant") == baseline).select("size", F.col("secs").alias("_b"))
    return times.join(F.broadcast(base), "size").select("variant", "size", "secs", (F.col("_b") / F.col("secs")).alias("speedup"))


def growth(times: DataFrame, by: str) -> DataFrame:
    """Factor of time from each value of a parameter to the next, for each variant."""
    w = Window.partitionBy("variant").orderBy(by)
    return times.select("variant", by, "secs", (F.col("secs") / F.lag("secs").over(w)).alias("factor"))


def scaling(times: DataFrame) -> DataFrame:
    """times(variant, threads, secs): how much faster a run is than on half the threads."""
    half = times.select("variant", (F.col("threads") * 2).alias("threads"), F.col("secs").alias("_half"))
    return times.join(half, ["variant", "threads"], "left").select("variant", "threads", "secs", (F.col("_half") / F.col("secs")).alias("factor"))


def cached_bytes(df: DataFrame) -> int:
    """Bytes that a cached table takes in memory and on disk, as the block manager reports them."""
    df.count()
    before = {i.id(): i for i in df.sparkSession.sparkContext._jsc.sc().getRDDStorageInfo()}
    return int(max((i.memSize() + i.diskSize() for k, i in before.items() if k == max(before)), default=0))


def outliers(runs: DataFrame, factor: float = 5.0) -> DataFrame:
    """runs(variant, seed, sweeps): marks runs with more than ``factor`` times the variant's median of sweeps."""
    mid = runs.groupBy("variant").agg(F.percentile("sweeps", F.lit(0.5)).alias("median"))
    return runs.join(F.broadcast(mid), "variant").withColumn("outlier", F.col("sweeps") > F.col("median") * factor)


def estimate_bytes(rows: int, row_bytes: int) -> int:
    """What decides between a broadcast and a co-partitioned join."""
    return rows * row_bytes
