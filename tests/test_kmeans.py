"""Points on a line, guards, ties, empty clusters and equality of layouts and exchanges."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from quiesce.operators import baselines as B
from quiesce.operators import kmeans as K
from quiesce.operators.packed import Kernel, pack_points, unpack_points
from quiesce.plans.policy import Exchange, Stop

LINE = [0, 1, 10, 11]


def line(spark, start):
    return spark.createDataFrame([(i, float(x), c) for i, (x, c) in enumerate(zip(LINE, start))], "pid long, x0 double, start int")


def clusters(run):
    return [r.c for r in run.state["assign"].orderBy("pid").collect()]


@pytest.mark.parametrize("start, preset", [((0, 1, 0, 1), "k1"), ((0, 0, 0, 1), "k4"), ((0, 1, 1, 1), "k5"), ((0, 0, 0, 1), "separate_buffered"), ((0, 1, 1, 1), "localized_indirect")])
def test_line(spark, start, preset):
    p = line(spark, start)
    run = K.kmeans(p, 2, init="column", start="start", **K.PRESETS[preset])
    assert clusters(run) == [0, 0, 1, 1] and run.reason == "quiet"
    assert K.sse(p, run.state["assign"], run.state["centers"]).first()[0] == pytest.approx(1)
    assert K.enabled_tuples(p, run.state["assign"], run.state["centers"]).first()[0] == 0


@pytest.mark.parametrize("layout", ["localized", "localized_blocks"])
def test_tie_rules_hold_in_every_kernel(spark, layout, monkeypatch):
    p = spark.createDataFrame([(0, 0.0, 0), (1, 2.0, 1), (2, 1.0, 0), (3, 1.0, 1), (4, -1.0, 0), (5, 3.0, 1)], "pid long, x0 double, start int")
    for limit in (256, 0)[layout.endswith("blocks") :]:  # unrolled expressions, then the block kernel
        monkeypatch.setattr(K, "UNROLLED", limit)
        for tie, want in (("stay", [0, 1, 0, 1, 0, 1]), ("last", [0, 1, 1, 1, 0, 1])):
            got = clusters(K.kmeans(p, 2, init="column", start="start", layout=layout, tie=tie, stop=Stop.max_iter(1), max_sweeps=1))
            assert got == want


@pytest.mark.parametrize("whole, preset", [(True, "k1"), (False, "k2"), (True, "k4"), (False, "k5")])
def test_blocks_equal_rows(spark, whole, preset):
    rng = random.Random(8)
    rows = [(i, rng.randrange(100), rng.randrange(100), rng.randrange(5)) for i in range(400)]
    kind = "long" if whole else "double"
    p = spark.createDataFrame([(str(i), a if whole else float(a) / 7, b if whole else float(b) / 3, c) for i, a, b, c in rows], f"pid string, x0 {kind}, x1 {kind}, start int").repartition(3)
    stop = {"stop": Stop.max_iter(3), "max_sweeps": 3}
    a = K.kmeans(p, 5, init="column", start="start", **K.PRESETS[preset], **stop)
    b = K.kmeans(p, 5, init="column", start="start", exchange="indirect", **stop)
    assert clusters(a) == clusters(b)
    for x, y in zip(a.state["centers"].orderBy("m").collect(), b.state["centers"].orderBy("m").collect()):
        assert tuple(x) == pytest.approx(tuple(y))


@pytest.mark.parametrize("local", ["frozen", "serial"])
def test_local_sweeps_settle(spark, local):
    rng = random.Random(2)
    p = spark.createDataFrame([(i, i % 3 * 50 + rng.random(), rng.randrange(3)) for i in range(300)], "pid long, x0 double, start int")
    run = K.kmeans(p, 3, init="column", start="start", shards=4, split="block", sweeps_per_exchange=3, local=local)
    assert K.enabled_tuples(p, run.state["assign"], run.state["centers"]).first()[0] == 0


@pytest.mark.parametrize("seed", range(8))
def test_local_moves_are_taken_one_at_a_time(seed):
    """Windows of points decide as single points do that see all moves before them."""
    r = np.random.default_rng(seed)
    k, d, n = int(r.integers(2, 7)), int(r.integers(1, 5)), 700
    x, c = (r.integers(0, 30, (d, n)) if seed % 2 else r.normal(size=(d, n))), r.integers(0, k, n).astype(np.int32)
    held = {m: (int((c == m).sum()), x[:, c == m].sum(axis=1).tolist()) for m in range(k)}
    kernel = Kernel(held, K.means(held), d, bool(seed % 2), "stay", "buffered", 2, "serial")
    size, total, want = kernel.n0.copy(), kernel.s0.copy(), c.copy()
    for _ in range(2):
        gap = ((x.T[:, None, :] - (total / size[:, None])[None]) ** 2).sum(axis=2)
        for i in np.flatnonzero(gap.min(axis=1) < gap[np.arange(n), want]):
            p, a = x[:, i], want[i]
            with np.errstate(divide="ignore", invalid="ignore"):
                now = np.where(size > 0, ((p - total / size[:, None]) ** 2).sum(axis=1), np.inf)
            b = int(now.argmin())
            if now[b] < now[a] and size[a] > 1:
                total[a], size[a], total[b], size[b], want[i] = total[a] - p, size[a] - 1, total[b] + p, size[b] + 1, b
    assert (kernel.local(x, c) == want).all()


def test_repeated_ids_count_once_after_local_sweeps(spark):
    p = spark.createDataFrame([("same", i % 2 * 50, (i + (i < 2)) % 2) for i in range(20)], "pid string, x0 long, start int")
    run = K.kmeans(p, 2, init="column", start="start", sweeps_per_exchange=4)
    assert [(r.m, r.n, r.c0) for r in run.state["centers"].orderBy("m").collect()] == [(0, 10, 0.0), (1, 10, 50.0)]


@pytest.mark.parametrize("split", ["range", "any", "block", "value"])
def test_tables_of_a_layout_lie_side_by_side(spark, split, monkeypatch):
    """Sweeps of separate tables shuffle no points, and the files of the one shuffle that dealt them out are gone; equal ids are points of their own."""
    tracker = spark.sparkContext._jsc.sc().env().mapOutputTracker()
    numbers = spark.range(0, 700, numPartitions=7)
    p = numbers.select((F.col("id") % 350).cast("string").alias("pid"), (F.col("id") % 3 * 50).alias("x0"), ((F.col("id") + (F.col("id") % 7 == 0).cast("int")) % 3).cast("int").alias("start"))
    number, deal, drawn = spark.sparkContext._jsc.sc().newShuffleId, K._blocks_of_ids, set()

    def noted(points, shards):  # the few ids that are drawn as bounds leave a small shuffle
        first, out = number(), deal(points, shards)
        drawn.update(range(first, number()))
        return out

    monkeypatch.setattr(K, "_blocks_of_ids", noted)
    before = number()
    runs = [K.kmeans(p, 3, init="column", start="start", layout=x, shards=4, split=split) for x in ("separate", "localized", "separate_blocks")]
    left = [tracker.getNumAvailableOutputs(i) for i in range(before + 1, number()) if i not in drawn and tracker.containsShuffle(i)]
    assert max(left, default=0) <= 4  # tables of points are read in 7 parts; sums come from 4
    for run in runs:
        assert [(r.m, r.n, r.c0) for r in run.state["centers"].orderBy("m").collect()] == [(0, 234, 0.0), (1, 233, 50.0), (2, 233, 100.0)]
        assert run.state["assign"].count() == 700
        run.release()


def test_separate_tables_join_in_place(spark):
    p = spark.range(0, 40, numPartitions=5).select(F.col("id").cast("string").alias("pid"), "id", (F.col("id") % 2 * 9).alias("x0"), (F.col("id") % 2).cast("int").alias("c"))
    engine = K._Columns(p, ["x0"], "separate", "stay", Exchange.buffered())
    with K.joined_in_place(spark):
        plan = engine._joined(engine.base)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan and "Sort [" not in plan
    blocks = K._Blocks(p, ["x0"], "separate_blocks", "stay", Exchange.buffered(), "serial")
    with K.joined_in_place(spark):
        plan = blocks._joined()._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan and "Sort [" not in plan
    engine.base = engine.base.withColumn("mark", F.lit(0))
    with pytest.raises(Exception, match="another order"):
        engine._joined(engine.base).collect()
    K.Run(spark, kept=engine.kept()).release()


def test_blocks_of_ids_stay_whole(spark):
    p = K._blocks_of_ids(spark.range(0, 4000, numPartitions=5).select(F.col("id").alias("pid")), 4)
    assert p._jdf.queryExecution().optimizedPlan().toString().count("Repartition") == 1
    shard = [r[0] for r in p.select(F.spark_partition_id().alias("s"), "pid").orderBy("pid").select("s").collect()]
    assert len(shard) == 4000 and 2 <= len(set(shard)) and 1 + sum(a != b for a, b in zip(shard, shard[1:])) <= 16


@pytest.mark.parametrize("top, wide", [(99, 1), (30_000, 2), (2_000_000, 4), (2**40, 8)])
def test_blocks_are_narrow(spark, top, wide):
    """Whole coordinates take as many bytes as they need; ids come back as they were."""
    for pid in ("long", "string"):
        p = spark.createDataFrame([(i, -(top * i // 49), i % 3, i % 2) for i in range(50)], "pid long, x0 long, x1 long, c int").withColumn("pid", F.col("pid").cast(pid)).coalesce(1)
        block = pack_points(p, ["x0", "x1"])
        r = block.first()
        assert (r.n, len(r.x)) == (50, 100 * wide)
        assert sorted(map(tuple, unpack_points(block, pid).collect())) == sorted((r.pid, r.c) for r in p.collect())
    engine = K._Blocks(p, ["x0", "x1"], "localized_blocks", "stay", Exchange.buffered(), "serial")
    assert engine.start() == {m: (25, [sum(-(top * i // 49) for i in range(m, 50, 2)), sum(i % 3 for i in range(m, 50, 2))]) for m in (0, 1)}


def test_library_baseline(spark):
    p = spark.createDataFrame([(i, float(i % 2 * 9)) for i in range(20)], "pid long, x0 double")
    run = B.baseline_kmeans_library(p, 2)
    assert sorted(r.n for r in run.state["centers"].collect()) == [10, 10]


def test_serial_error_falls_with_every_move():
    rng = random.Random(4)
    rows = [((rng.gauss(c * 4, 1), rng.gauss(0, 1)), rng.randrange(3)) for c in range(3) for _ in range(30)]
    for seed in range(4):
        r = random.Random(seed)
        _, errors, _ = K.kmeans_serial(rows, 3, order=lambda n, r=r: r.sample(range(n), n))
        assert all(b < a + 1e-9 for a, b in zip(errors, errors[1:]))


def test_serial_moves_by_hand():
    assert K.kmeans_serial([((x,), c) for x, c in zip(LINE, (0, 1, 0, 1))], 2)[0] == [0, 0, 1, 1]


def test_singletons_and_ties(spark):
    one = spark.createDataFrame([(0, 0.0, 0), (1, 2.0, 1), (2, 1.0, 0)], "pid long, x0 double, start int")
    # point 2 lies at 0.5 from its own mean and at 1 from the other: it stays
    assert clusters(K.kmeans(one, 2, init="column", start="start")) == [0, 1, 0]
    tied = spark.createDataFrame([(0, 0.0, 0), (1, 2.0, 1)], "pid long, x0 double, start int")
    mid = spark.createDataFrame([(9, 1.0)], "pid long, x0 double")
    run = K.kmeans(tied, 2, init="column", start="start")
    assert K.assign(mid, run.state["centers"]).first()["c"] == 0


@pytest.mark.parametrize("empty", ["keep", "drop", "reseed"])
def test_empty_cluster(spark, empty):
    p = spark.createDataFrame([(0, 0.0, 0), (1, 0.1, 1), (2, 0.2, 0), (3, 50.0, 2)], "pid long, x0 double, start int")
    run = K.kmeans(p, 3, init="column", start="start", empty=empty, exchange="indirect", stop=Stop.max_iter(4), max_sweeps=4)
    assert run.state["assign"].count() == 4
    assert sum(r.n for r in run.state["centers"].collect()) == 4


def test_bad_input(spark):
    with pytest.raises(ValueError):
        K.kmeans(line(spark, (0, 0, 0, 0)), 0)
    with pytest.raises(ValueError, match="NaN"):
        K.kmeans(spark.createDataFrame([(0, float("nan"))], "pid long, x0 double"), 1)


def test_block_kernel_equals_unrolled(spark, monkeypatch):
    p = spark.createDataFrame([(i, float(i % 7), float(i % 5), i % 3) for i in range(60)], "pid long, x0 double, x1 double, start int")
    a = clusters(K.kmeans(p, 3, init="column", start="start", stop=Stop.max_iter(2), max_sweeps=2))
    monkeypatch.setattr(K, "UNROLLED", 0)
    assert a == clusters(K.kmeans(p, 3, init="column", start="start", stop=Stop.max_iter(2), max_sweeps=2))


def test_baselines_agree(spark):
    p = line(spark, (0, 1, 0, 1))
    want = [0, 0, 1, 1]
    assert clusters(B.baseline_kmeans_mr(p, 2)) == want and clusters(B.baseline_kmeans_bsp(p, 2)) == want


def test_inits_do_not_depend_on_partitions(spark):
    p = line(spark, (0, 0, 0, 0))
    for init in ("random_assign", "mod", "sample"):
        a = [r.c for r in K.initial(p, 2, init).orderBy("pid").collect()]
        assert a == [r.c for r in K.initial(p.repartition(3), 2, init).orderBy("pid").collect()]


@pytest.mark.parametrize("exchange", ["immediate", Exchange.immediate(), "bufferd"])
def test_exchanges_that_sweeps_do_not_have_are_refused(spark, exchange):
    points = spark.createDataFrame([("a", 0.0), ("b", 1.0)], "pid string, x0 double")
    with pytest.raises(ValueError, match="exchange"):
        K.kmeans(points, 2, exchange=exchange)
