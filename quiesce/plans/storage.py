"""Lineage cuts that survive lost executors."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only in local mode and where the session names none."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    if sc.getCheckpointDir() is None:
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="quiesce-checkpoint-"))
    return named or sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: a restart point, and an end to the growth of the plan."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def leaf(df: DataFrame) -> DataFrame:
    """The same rows as a leaf of later plans: their plans stay as small as one sweep's, and lost partitions are still recomputed.

    This is what a checkpoint does to a plan, without writing; partitioning and statistics stay known.
    """
    spark = df.sparkSession
    jdf, jvm = df._jdf, spark.sparkContext._jvm
    made = getattr(getattr(jvm.org.apache.spark.sql.execution, "LogicalRDD$"), "MODULE$")
    data = getattr(getattr(jvm.org.apache.spark.sql.classic, "Dataset$"), "MODULE$")
    plan = made.fromDataset(jdf.queryExecution().toRdd(), jdf, False)
    return DataFrame(data.ofRows(spark._jsparkSession, plan), spark)


def _known(df: DataFrame, parts: int) -> DataFrame:
    """``leaf``, known to be dealt out by its column shard and sorted by shard and at, as ``dealt`` has numbered it."""
    spark = df.sparkSession
    jvm, made = spark.sparkContext._jvm, df._jdf.queryExecution()
    catalyst, toSeq = jvm.org.apache.spark.sql.catalyst, jvm.org.apache.spark.api.python.PythonUtils.toSeq
    one = lambda name: getattr(getattr(catalyst.expressions, name + "$"), "MODULE$")
    output = made.analyzed().output()
    of = {output.apply(i).name(): output.apply(i) for i in range(output.size())}
    by, order = jvm.java.util.ArrayList(), jvm.java.util.ArrayList()
    by.add(of["shard"])
    for name in ("shard", "at"):
        order.add(catalyst.expressions.SortOrder(of[name], one("Ascending"), one("NullsFirst"), toSeq(jvm.java.util.ArrayList())))
    none = jvm.scala.Option.empty()
    plan = jvm.org.apache.spark.sql.execution.LogicalRDD(output, made.toRdd(), catalyst.plans.physical.HashPartitioning(toSeq(by), parts), toSeq(order), False, none, spark._jsparkSession, none, none)
    data = getattr(getattr(jvm.org.apache.spark.sql.classic, "Dataset$"), "MODULE$")
    return DataFrame(data.ofRows(spark._jsparkSession, plan), spark)


@contextmanager
def joined_in_place(spark: SparkSession) -> Iterator[None]:
    """Joins by (shard, at) that are planned inside take tables dealt out by shard alone as they lie."""
    name = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(name)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, before)


class Dealt:
    """A kept table and tables made from its rows, which join by (shard, at) with no shuffle and no sort (``joined_in_place``).

    at is a row's place in its partition. shard is a number that the hash deals out to just this
    partition, so what the plans are told of the partitioning is true for any way to split.
    """

    def __init__(self, kept: DataFrame) -> None:
        rows, spark = leaf(kept), kept.sparkSession
        self.parts = rows._jdf.queryExecution().toRdd().getNumPartitions()
        labels, n = {}, 32 * self.parts
        while len(labels) < self.parts:
            numbers = spark.range(n, numPartitions=1).select(F.col("id").cast("int").alias("v"))
            labels = {r[0]: r[1] for r in numbers.groupBy(F.pmod(F.hash("v"), F.lit(self.parts)).alias("p")).agg(F.min("v")).collect()}
            n *= 4
        shard = F.array(*(F.lit(labels[i]) for i in range(self.parts)))[F.spark_partition_id()]
        place = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
        self.rows = self.known(rows.select(shard.alias("shard"), place.alias("at"), *rows.columns))

    def known(self, df: DataFrame) -> DataFrame:
        """A table with columns shard and at whose partitions are still those of ``rows``."""
        return _known(df, self.parts)


def free_shuffles(kept: DataFrame) -> None:
    """Deletes the shuffle files that a kept table was made from; if a part of it is lost, they are written again."""
    sc = kept.sparkSession.sparkContext
    cleaner = sc._jsc.sc().cleaner()
    if cleaner.isEmpty():
        return
    todo, seen, met = [(kept._jdf.queryExecution().toRdd(), False)], set(), set()
    while todo:
        rdd, inside = todo.pop()
        if rdd.id() in seen:
            continue
        seen.add(rdd.id())
        stored = rdd.getStorageLevel().useMemory() or rdd.getStorageLevel().useDisk()
        if stored and inside:  # another kept table, which may not be complete
            continue
        needs = rdd.dependencies()
        for i in range(needs.size()):
            need = needs.apply(i)
            if need.getClass().getSimpleName() == "ShuffleDependency":
                met.add(need.shuffleId())
            todo.append((need.rdd(), inside or stored))
    for number in met:
        cleaner.get().doCleanupShuffle(number, True)


class States:
    """States of a loop: kept in memory or on disk between sweeps, cut every few sweeps, old ones released.

    Kept as columns: serialised, they lie in chunks of 1 MB and a header, which take two of
    the garbage collector's regions each and so twice the memory that Spark counts.
    """

    def __init__(self, every: int = 5) -> None:
        self.every, self.n, self.held = every, 0, []

    def next(self, df: DataFrame, important: bool = False) -> DataFrame:
        """Keeps the new state; the one before the last is released."""
        self.n += 1
        if important or self.n % self.every == 0:
            out = cut(df)
            self.held.append(out)
        else:
            kept = df.persist(StorageLevel.MEMORY_AND_DISK_DESER)
            self.held.append(kept)
            out = leaf(kept)
        if len(self.held) > 2:
            self.held.pop(0).unpersist()
        return out

    def close(self) -> None:
        """Releases all but the last state, which the result still reads."""
        for df in self.held[:-1]:
            df.unpersist()
        self.held = self.held[-1:]
