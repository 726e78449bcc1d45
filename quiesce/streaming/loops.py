"""New points and edges as streams, and windows over events.

Since updates commute and stale copies are tolerated, a batch of new tuples is just
more tuples: centres take their moves, ranks keep what they remember and settle again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.kmeans import Centres, centre_frame, dims, means
from ..functions.vectors import nearest, sqdist
from ..plans.policy import Stop
from ..plans.storage import cut, shared_dir


def _drain(writer) -> None:
    q = writer.trigger(availableNow=True).start()
    q.awaitTermination()


def _place(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def minibatch_kmeans(stream: DataFrame, centres: Centres) -> Centres:
    """Each batch's points join their nearest centre; sums and counts grow by the batch's deltas (k rows to the driver)."""
    xs, state = dims(stream), dict(centres)

    def take(batch: DataFrame, _: int) -> None:
        best = nearest([(m, sqdist(xs, c)) for m, c in means(state)])["m"]
        for r in batch.select(*xs, best.alias("m")).groupBy("m").agg(F.count(F.lit(1)).alias("n"), *(F.sum(x).alias(x) for x in xs)).collect():
            n, s = state.get(r["m"], (0, [0] * len(xs)))[:2]
            state[r["m"]] = (n + r["n"], [a + r[x] for a, x in zip(s, xs)])

    _drain(stream.writeStream.foreachBatch(take).option("checkpointLocation", _place(stream.sparkSession, "km")))
    return state


def incremental_rank(stream: DataFrame, known: DataFrame, **options) -> DataFrame:
    """Ranks at rest after all batches of new edges.

    A batch appends only its new edges to the folder of known ones. The program then starts
    from the last ranks, as edges that have passed them on already, and settles again, so a
    batch that changes little needs few sweeps.
    """
    from ..operators.rank import rank

    spark = stream.sparkSession
    folder = _place(spark, "edges")
    known.select("u", "v").distinct().write.parquet(f"{folder}/batch=-1")
    schema = spark.read.parquet(f"{folder}/batch=-1").schema
    held: dict = {"ranks": None}

    def edges() -> DataFrame:
        return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(folder)

    def take(batch: DataFrame, i: int) -> None:
        batch.select("u", "v").distinct().write.mode("overwrite").parquet(f"{folder}/batch={i}")
        run = rank(edges(), **({"memory": "adjacency", "known": held["ranks"], "stop": Stop.residual(1e-9), "max_sweeps": 400} | options))
        held["ranks"] = cut(run.state["ranks"])

    _drain(stream.writeStream.foreachBatch(take).option("checkpointLocation", _place(spark, "rank")))
    return held["ranks"] if held["ranks"] is not None else rank(edges(), **options).state["ranks"]


def _table(spark: SparkSession, df: DataFrame, mode: str = "append") -> DataFrame:
    """The rows of a streaming query once its source is drained, written to the shared folder."""
    out = _place(spark, "stream")
    schema = df.schema

    def take(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={i}")

    _drain(df.writeStream.outputMode(mode).foreachBatch(take).option("checkpointLocation", _place(spark, "check")))
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(out)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*").withColumn("at", F.col("ts").cast("timestamp"))


def windowed_counts(stream: DataFrame, width: str = "1 day", late: str = "0 seconds") -> DataFrame:
    """Tumbling windows per event type, complete output: start, event_type, n, total (hundredths)."""
    rows = stream.withWatermark("at", late).groupBy(F.window("at", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("total"))
    out = _table(stream.sparkSession, rows.select(F.col("window.start").alias("start"), "event_type", "n", "total"), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n", "total")


def sessions(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Session windows of users, complete output: user_id, n."""
    rows = stream.withWatermark("at", "0 seconds").groupBy(F.session_window("at", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    out = _table(stream.sparkSession, rows.select("user_id", F.col("session_window.start").alias("s"), "n"), "complete")
    return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


def first_seen(stream: DataFrame, late: str = "365 days") -> DataFrame:
    """One row per (user, type): duplicates within the watermark are dropped."""
    rows = stream.withWatermark("at", late).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return _table(stream.sparkSession, rows)


__all__ = ["minibatch_kmeans", "incremental_rank", "event_stream", "windowed_counts", "sessions", "first_seen", "centre_frame"]
