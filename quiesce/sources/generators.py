"""Generated inputs; every value is a hash of its row number, so partitions do not matter."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _uniform(*parts) -> Column:
    """A number in (0, 1) from a hash."""
    h = F.xxhash64(*(p if isinstance(p, Column) else F.lit(p) for p in parts))
    return (F.shiftrightunsigned(h, 12).cast("double") + 0.5) / float(1 << 52)


def _normal(*parts) -> Column:
    return F.sqrt(-2 * F.log(_uniform(*parts, "r"))) * F.cos(2 * math.pi * _uniform(*parts, "a"))


def gen_gaussian(spark: SparkSession, n: int, d: int = 4, k: int = 4, box: tuple[float, float] = (0.0, 10.0), seed: int = 0) -> DataFrame:
    """pid, x0.., truth: normal clusters; centres uniform in the box (our choice of box), deviations uniform in [10/16, 10/8]."""
    rows = spark.range(n).withColumnRenamed("id", "pid").withColumn("truth", F.floor(_uniform(seed, "c", F.col("pid")) * k).cast("int"))
    low, high = box
    spread = F.lit(10 / 16) + _uniform(seed, "s", F.col("truth")) * (10 / 8 - 10 / 16)
    xs = [(low + (high - low) * _uniform(seed, "m", F.col("truth"), j) + spread * _normal(seed, "x", F.col("pid"), j)).alias(f"x{j}") for j in range(d)]
    return rows.select("pid", *xs, "truth")


def gen_kron(spark: SparkSession, levels: int, n_edges: int, initiator: tuple[float, float, float, float] = (0.57, 0.19, 0.19, 0.05), seed: int = 0) -> DataFrame:
    """u, v in [0, 2^levels): each edge picks one quadrant of the adjacency matrix per level. Isolated vertices may remain."""
    a, b, c, _ = initiator
    u, v = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(levels):
        p = _uniform(seed, level, F.col("id"))
        u = u * 2 + F.when(p >= a + b, 1).otherwise(0)
        v = v * 2 + F.when((p >= a) & (p < a + b) | (p >= a + b + c), 1).otherwise(0)
    return spark.range(n_edges).select(u.alias("u"), v.alias("v")).distinct()
