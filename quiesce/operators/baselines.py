"""The hand-written competitors, as Spark programs of the same style.

The map-reduce forms write the whole state to disk and read it back in every
iteration, and ship every (key, value) pair without combining first; the bulk forms
keep data in memory and run two barriers per iteration.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import last_nearest, sqdist
from ..plans.policy import Stop
from ..plans.runtime import Clock, Run
from ..plans.storage import shared_dir
from ..sources.tables import degrees, vertices_of
from .kmeans import _shift, centre_frame, dims, initial, kmeans_classic, means, summed
from .rank import rank, rank_classic


def _round_trip(df: DataFrame, folder: str) -> DataFrame:
    df.write.parquet(folder)
    return df.sparkSession.read.parquet(folder)


def _uncombined(df: DataFrame, key: str) -> DataFrame:
    """Ships all pairs by key before any of them meet."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(parts, key)


def baseline_kmeans_mr(points: DataFrame, k: int, *, start: str = "start", delta: float = 1e-4, max_iter: int = 10) -> Run:
    spark, xs, clock = points.sparkSession, dims(points), Clock()
    folder = f"{shared_dir(spark).rstrip('/')}/mr-{uuid.uuid4().hex}"
    rows = _round_trip(initial(points, k, "column", start=start).select("pid", *xs, "c"), f"{folder}/0")
    centres, log, reason = summed(rows), [], "sweeps"
    for i in range(1, max_iter + 1):
        best = last_nearest([(m, sqdist(xs, c)) for m, c in means(centres)])["m"]
        rows = _round_trip(_uncombined(rows.select("pid", *xs, best.alias("c")), "c"), f"{folder}/{i}")
        new = summed(rows)
        shift = _shift(centres, new)
        centres = new
        log.append({"sweeps": i, "shift": shift, "secs": clock.lap()})
        if shift < delta:
            reason = "shift"
            break
    return Run(spark, {"centers": centre_frame(spark, centres, xs), "assign": rows.select("pid", "c")}, log, reason)


def baseline_kmeans_bsp(points: DataFrame, k: int, *, start: str = "start", theta: float = 1e-4, max_iter: int = 500) -> Run:
    return kmeans_classic(points.persist(), k, init="column", start=start, stop=Stop.any(Stop.switch_fraction(theta), Stop.max_iter(max_iter)), max_sweeps=max_iter)


def baseline_rank_mr(edges: DataFrame, *, d: float = 0.85, eps: float = 1e-6, max_iter: int = 10) -> Run:
    spark, clock = edges.sparkSession, Clock()
    folder = f"{shared_dir(spark).rstrip('/')}/mr-{uuid.uuid4().hex}"
    vertices, links = vertices_of(edges), _round_trip(edges.join(degrees(edges), "u"), f"{folder}/edges")
    n = vertices.count()
    ends = degrees(edges).withColumnRenamed("u", "id")
    ranks = _round_trip(vertices.join(ends, "id", "left").select("id", F.lit(1.0 / n).alias("pr"), F.col("dout").isNull().alias("lone")), f"{folder}/0")
    log, reason = [], "sweeps"
    for i in range(1, max_iter + 1):
        pairs = links.join(ranks.select(F.col("id").alias("u"), "pr"), "u").select("v", (F.col("pr") / F.col("dout")).alias("x"))
        sums = _uncombined(pairs, "v").groupBy(F.col("v").alias("id")).agg(F.sum("x").alias("x"))
        lone = ranks.filter("lone").agg(F.coalesce(F.sum("pr"), F.lit(0.0))).first()[0]
        own = F.when(F.col("lone"), F.col("pr")).otherwise(0.0)
        new = ranks.join(sums, "id", "left").select("id", (F.lit((1 - d) / n) + d * (F.coalesce("x", F.lit(0.0)) + (F.lit(lone) - own) / (n - 1))).alias("pr"), "lone", F.col("pr").alias("was"))
        new = _round_trip(new, f"{folder}/{i}")
        change = new.agg(F.sum(F.abs(F.col("pr") - F.col("was")))).first()[0]
        ranks = new.drop("was")
        log.append({"sweeps": i, "change": change, "residual": change, "secs": clock.lap()})
        if change < eps:
            reason = "change"
            break
    return Run(spark, {"ranks": ranks.select("id", "pr")}, log, reason)


def baseline_rank_bsp(edges: DataFrame, *, d: float = 0.85, eps: float = 0.0, max_iter: int = 10) -> Run:
    return rank_classic(edges, d=d, eps=eps, max_iter=max_iter)


def baseline_rank_naive(edges: DataFrame, **options) -> Run:
    """The program as first written: a memory for each edge in a table of its own, over all added edges."""
    return rank(edges, variant="edge_delta", **options)


def baseline_kmeans_library(points: DataFrame, k: int, *, seed: int = 0, max_iter: int = 20) -> Run:
    """The platform's own k-Means, for a comparison of quality."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    spark, xs, clock = points.sparkSession, dims(points), Clock()
    rows = points.select("pid", *xs, array_to_vector(F.array(*(F.col(x).cast("double") for x in xs))).alias("features"))
    model = KMeans(k=k, seed=seed, maxIter=max_iter, initSteps=2).fit(rows)
    found = model.transform(rows).select("pid", *xs, F.col("prediction").alias("c"))
    log = [{"sweeps": i + 1, "sse": model.summary.trainingCost, "secs": clock.lap()} for i in range(model.summary.numIter)]
    return Run(spark, {"centers": centre_frame(spark, summed(found), xs), "assign": found.select("pid", "c")}, log, "library")
