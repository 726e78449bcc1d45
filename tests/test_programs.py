"""Transformations, small programs, sources and generators."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from quiesce import queries as Q
from quiesce.operators import kmeans as K
from quiesce.operators import programs as P
from quiesce.operators import rank as R
from quiesce.plans import spec as L
from quiesce.plans.policy import Exchange, Schedule, Stop
from quiesce.sources import generators as G
from quiesce.sources import textfiles as X


def test_legality():
    k, r = L.kmeans_spec(), L.rank_spec()
    with pytest.raises(L.IllegalStep):
        L.fold(k, "dangling")
    with pytest.raises(L.IllegalStep):
        L.fix_layout(k, "wide_columns")
    with pytest.raises(L.IllegalStep):
        L.group_by_field(L.fix_layout(L.index_reservoir(r), "wide_columns"), "v")
    with pytest.raises(L.IllegalStep):
        L.embed(r, "nothing")
    with pytest.raises(L.IllegalStep):
        L.shard(r, 4, "u", cover="overlap")
    with pytest.raises(L.IllegalStep):
        L.interchange(L.group_by_field(r, "u", "v"), "u", "v")
    with pytest.raises(L.IllegalStep):
        L.exchange_by(r, Exchange.indirect())
    assert L.single_writer(L.group_by_field(r, "v"), "pr") and not L.single_writer(L.group_by_field(r, "u"), "pr")
    assert L.combine_updates([(("a",), 1), (("a",), 2)]) == {("a",): 3}
    assert "settle rank" in L.rank_spec().explain()


def test_derived_programs_run(spark):
    tri = spark.createDataFrame([(1, 2), (1, 3), (2, 3)], "u long, v long")
    s = L.fix_layout(L.index_reservoir(L.fold(L.shard(L.embed(L.group_by_field(L.rank_spec(), "v"), "old"), 2, "v"), "dangling")), "wide_columns")
    run = R.rank(tri, stop=Stop.max_iter(1), max_sweeps=1, **L.rank_options(s))
    assert {r.id: r.pr for r in run.state["ranks"].collect()} == pytest.approx({1: 57 / 800, 2: 37 / 400, 3: 91 / 800})
    k = L.kmeans_spec()
    for name in ("cluster", "coordinates"):
        k = L.embed(k, name)
    k = L.fix_layout(L.exchange_by(L.index_reservoir(L.shard(k, 2, "x")), Exchange.indirect()), "array_rows")
    assert L.kmeans_options(k) == {"layout": "localized_blocks", "exchange": "indirect", "sweeps_per_exchange": 1, "shards": 2, "split": "value"}


def test_derived_clusterings_leave_nothing_in_memory(spark, monkeypatch):
    """A run's tables are released before the next run, so that memory does not grow with the number of plans."""
    rows = [(str(i), 1000 * (i % 4) + i // 4, i % 4, (i + (i % 7 == 0)) % 4) for i in range(80)]
    p = spark.createDataFrame(rows, "pid string, x0 long, truth int, start int")
    monkeypatch.setattr(Q.T, "anchored", lambda spark, sf_dir: p)
    held, run, most = spark.sparkContext._jsc.getPersistentRDDs, Q.K.kmeans, []
    before = set(held())

    def watched(*args, **options):
        most.append(len(set(held()) - before))
        return run(*args, **options)

    monkeypatch.setattr(Q.K, "kmeans", watched)
    got = Q.derived_kmeans(spark, "")
    assert len(most) == 15 and set(most) == {0} and set(held()) <= before
    assert sorted((r.m, r.size, r.c0) for r in got.collect()) == [(m, 20, 1000 * m + 9.5) for m in range(4)]


def test_every_different_clustering_runs(spark, monkeypatch):
    """Each layout with each exchange, without shards and with each way to split: 60 plans, and 20 that sweep four times between exchanges."""
    rows = [(str(i), 1000 * (i % 4) + i // 4, i % 4, (i + (i % 7 == 0)) % 4) for i in range(80)]
    p = spark.createDataFrame(rows, "pid string, x0 long, truth int, start int")
    monkeypatch.setattr(Q.T, "anchored", lambda spark, sf_dir: p)
    run = Q.K.kmeans
    ran, at_rest = [], run(p, 4, init="column", start="start")

    def noted(points, k, **options):
        ran.append(tuple(options[x] for x in ("layout", "exchange", "sweeps_per_exchange", "shards", "split")))
        return run(points, k, **options) if options["sweeps_per_exchange"] > 1 and options["shards"] is None else at_rest

    monkeypatch.setattr(Q.K, "kmeans", noted)
    got = Q.derived_kmeans(spark, "")
    once = {(layout.removesuffix("_blocks") if n > 1 else layout, x, n, shards, split if shards else "") for layout, x, n, shards, split in ran}
    covers = [(None, ""), *((4, split) for split in ("any", "value", "range", "block"))]
    want = {(layout + b, x, 1, *c) for layout in ("separate", "localized") for b in ("", "_blocks") for x in ("buffered", "master", "indirect") for c in covers}
    want |= {(layout, x, 4, *c) for layout in ("separate", "localized") for x in ("buffered", "master") for c in covers}
    assert once == want and len(ran) == len(want) == 80
    assert sorted((r.m, r.size, r.c0) for r in got.collect()) == [(m, 20, 1000 * m + 9.5) for m in range(4)]


def test_diagonal_chain():
    s = L.diagonal_product("padded")
    assert L.product_layout(s) == "padded" and s.order == ("k", "i") and len(s.steps) == 5
    plain = L.fix_layout(L.index_reservoir(L.product_spec()), "padded")
    with pytest.raises(L.IllegalStep):
        L.product_layout(plain)


def test_cheapest_forms():
    best = L.ranked(L.rank_spec(), {"vertices": 1e6, "edges": 1e7, "dangling": 1e5})[0]
    assert best.folded and "old" in best.embedded and L.single_writer(best, "pr")
    k = L.ranked(L.kmeans_spec(), {"points": 1e6, "k": 4, "d": 4})[0]
    assert {"cluster", "coordinates"} <= set(k.embedded) and k.exchange.kind == "buffered" and "x" in k.order


def test_sparse_layouts(spark):
    rng = random.Random(1)
    cells = sorted({(rng.randrange(12), rng.randrange(9)): rng.randrange(1, 9) for _ in range(60)}.items())
    a = spark.createDataFrame([(i, j, v) for (i, j), v in cells] + [(40, 77, 5)], "i long, j long, val long")
    b = spark.createDataFrame([(j, j * 2, 7 - j) for j in range(9)], "j long, c0 long, c1 long")
    want: dict = {}
    for (i, j), v in cells:
        x, y = want.get(i, (0, 0))
        want[i] = (x + v * j * 2, y + v * (7 - j))
    for layout in ("coo", "row_lists", "padded", "jagged"):
        assert {r.i: (r.c0, r.c1) for r in P.spmm(a, b, layout).collect()} == want, layout
    assert {r.i: (r.c0, r.c1) for r in P.spmm(a, b, "jagged", bound=0).collect()} == want  # too large to replicate
    product = {(r.i, r.j): r.val for r in P.matmul(a, b.select(F.col("j").alias("i"), F.lit(0).alias("j"), F.col("c0").alias("val"))).collect()}
    assert product == {(i, 0): x for i, (x, _) in want.items()}


def test_layouts_hold_their_order(spark):
    a = spark.createDataFrame([(0, 0, 1), (0, 2, 2), (1, 1, 3), (2, 0, 4), (2, 1, 5), (2, 2, 6)], "i long, j long, val long")
    blocks = {x: P.pack_rows(a, x, np.arange(3), parts=1).first() for x in ("row_lists", "padded", "jagged")}
    vals = {x: np.frombuffer(r["vals"]).tolist() for x, r in blocks.items()}
    assert vals == {"row_lists": [1, 2, 3, 4, 5, 6], "padded": [1, 3, 4, 2, 0, 5, 0, 0, 6], "jagged": [4, 1, 3, 5, 2, 6]}
    assert np.frombuffer(blocks["jagged"]["rows"], np.int64).tolist() == [2, 0, 1]


def test_overlapping_cover_takes_minima_only(spark):
    df = spark.createDataFrame([(k, k % 5) for k in range(100)], "u long, v long")
    shards = P.covers(F.col("u"), 8, 0, 99, 6)
    assert df.select(F.size(shards).alias("n")).agg(F.max("n")).first()[0] > 1
    assert {r.v: r.value for r in P.once_covered(df, shards, ["v"], F.col("u")).collect()} == {k: k for k in range(5)}
    with pytest.raises(ValueError):
        P.once_covered(df, shards, ["v"], F.col("u"), "sum")


def test_plans_do_not_grow_with_sweeps(spark):
    from quiesce.plans.storage import States

    states, sizes = States(50), []
    df = states.next(spark.range(10).withColumn("x", F.lit(1.0)))
    for _ in range(4):
        df = states.next(df.join(df.withColumnRenamed("x", "y"), "id").selectExpr("id", "x + y as x"))
        sizes.append(len(df._jdf.queryExecution().logical().toString()))
    assert sizes[-1] <= sizes[0] + 50 and {r.x for r in df.collect()} == {16.0}
    states.close()


def test_measures(spark):
    from quiesce.functions import measures as Q

    t = spark.createDataFrame([("x", 1, 4.0), ("x", 2, 2.5), ("x", 4, 2.0)], "variant string, threads int, secs double")
    assert {r.threads: r.factor for r in Q.scaling(t).collect()} == {1: None, 2: 1.6, 4: 1.25}


def test_sorts(spark):
    values = [5, 3, 3, 9, 1, 3]
    df = spark.createDataFrame(list(enumerate(values)), "slot long, value long")
    for f in (P.sort_builtin, P.sort_neighbours, P.sort_all_pairs):
        assert [r.value for r in f(df).orderBy("slot").collect()] == sorted(values)


def test_shards_cover(spark):
    df = spark.range(0, 101).toDF("v")
    got = df.select(P.shard_of(F.col("v"), 8, "range", 0, 100).alias("s")).groupBy("s").count().collect()
    assert sum(r["count"] for r in got) == 101 and {r.s for r in got} == set(range(8))


def test_settle(spark):
    state, n = P.settle(spark.createDataFrame([(5,), (2,)], "x int"), lambda s: s.select(F.when(F.col("x") > 0, F.col("x") - 1).otherwise(F.col("x")).alias("x")), F.col("x") > 0)
    assert n == 5 and {r.x for r in state.collect()} == {0}


def test_text_formats(spark, tmp_path):
    p = spark.createDataFrame([(7, 1.5, -2e-3), (8, 0.0, 4.0)], "pid long, x0 double, x1 double")
    X.write_points(p, str(tmp_path / "a"), True)
    good, bad = X.read_points(spark, str(tmp_path / "a"), 2, True)
    assert sorted(map(tuple, good.collect())) == [(7, 1.5, -0.002), (8, 0.0, 4.0)] and bad.count() == 0
    (tmp_path / "b.txt").write_text("1.0 2.0\nx 2\n\n1e3 -4\n1 2 3\n")
    good, bad = X.read_points(spark, str(tmp_path / "b.txt"), 2, False)
    assert good.count() == 2 and {r.line for r in bad.collect()} == {"x 2", "1 2 3"}
    X.write_edges(spark.createDataFrame([(1, 2)], "u long, v long"), str(tmp_path / "e"))
    assert X.read_edges(spark, str(tmp_path / "e")).collect() == [(1, 2)]
    X.snapshot(p, str(tmp_path / "s"), 3)
    X.snapshot(p.limit(1), str(tmp_path / "s"), 10)
    again, sweep = X.resume(spark, str(tmp_path / "s"))
    assert sweep == 10 and again.count() == 1


def test_generators_do_not_depend_on_partitions(spark):
    a = G.gen_gaussian(spark, 500, seed=3)
    assert a.exceptAll(G.gen_gaussian(spark, 500, seed=3).repartition(7)).count() == 0
    e = G.gen_kron(spark, 6, 400)
    assert e.filter("u < 0 or u >= 64 or v >= 64").count() == 0
    top = e.groupBy("u").count().agg(F.max("count")).first()[0]
    assert top > 3 * 400 / 64  # heavy-tailed


def test_stops_and_schedules(spark):
    assert Stop.any(Stop.max_iter(3), Stop.residual(0.1)).reason({"sweeps": 1, "residual": 0.05, "enabled": 1}) == "residual"
    assert Stop.quiet().reason({"enabled": 0, "full": False}) is None and Stop.quiet().reason({"enabled": 0}) == "quiet"
    n = spark.range(1000).filter(Schedule.sample(0.3, 1).runs(F.col("id"), 4)).count()
    assert 200 < n < 400
    assert K.PRESETS.keys() >= {"k1", "k2", "k3", "k4", "k5"}
