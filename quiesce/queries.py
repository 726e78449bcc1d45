"""Queries over the given tables for every method, variant, baseline, measure and workload, with SQL where it can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import sqltext as S
from .operators import baselines as B
from .operators import kmeans as K
from .operators import programs as P
from .operators import rank as R
from .operators import relational
from .plans import spec as L
from .plans.policy import Schedule, Stop
from .sources import generators as G
from .sources import tables as T
from .streaming import loops as W
from . import workloads as X

QUERIES: dict = dict(relational.QUERIES)
ORACLES: dict[str, str] = dict(relational.ORACLES)
SWEEPS = 8  # of the forms that are compared sweep by sweep, and of their SQL
CLASSIC = 20
REST = 120  # sweeps of the SQL that stands for the fixpoint: 0.85^120 is below 4e-9


def _add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


# ---- k-Means


def _centres(run) -> DataFrame:
    c = run.state["centers"]
    return c.select("m", F.col("n").alias("size"), *(F.round(x, 6).alias(x) for x in c.columns[2:]))


def _km(name: str, points, sql: str, d: int, k: int, sweeps: int, tie: str = "stay", **options) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        f = K.kmeans_classic if tie == "last" else K.kmeans
        return _centres(f(points(spark, sf_dir), k, init="column", start="start", tie=tie, stop=Stop.max_iter(sweeps), max_sweeps=sweeps, **options))

    _add(name, run, S.kmeans_centres(sql, d, k, sweeps, tie))


_km("km_classic_lineitem", T.lineitem_started, S.POINTS["started"], 4, 4, 5, "last")
_km("km_moves_lineitem", T.lineitem_started, S.POINTS["started"], 4, 4, 4)
_km("km_moves_blocks", T.lineitem_started, S.POINTS["started"], 4, 4, 4, layout="localized_blocks")
for _d in (4, 8, 16, 32, 64):
    _km(f"km_embeddings_d{_d}", lambda s, f, d=_d: T.embeddings(s, f, d, 4), S.embedding_points(_d), _d, 4, 3, layout="localized_blocks")
for _k in (2, 4, 8, 16, 32):
    _km(f"km_k_sweep_{_k}", lambda s, f, k=_k: T.lineitem_started(s, f, k), S.POINTS["started"], 4, _k, 3, layout="separate_blocks", empty="drop")
_km("km_events_features", lambda s, f: T.event_users(s, f, 3), S.POINTS["events"], 4, 3, 3)
_km("km_documents_features", lambda s, f: T.document_shape(s, f, 3), S.POINTS["documents"], 4, 3, 3)
_km("km_customer_rfm", lambda s, f: T.customer_activity(s, f, 3), S.POINTS["customers"], 3, 3, 3)

_TRUTH = f"SELECT truth AS m, CAST(count(*) AS BIGINT) AS size, {', '.join(f'round(CAST(sum(x{j}) AS DOUBLE) / count(*), 6) AS c{j}' for j in range(4))} FROM ({S.POINTS['anchored']}) GROUP BY truth"


def _settled(name: str, **options) -> None:
    _add(name, lambda spark, sf_dir: _centres(K.kmeans(T.anchored(spark, sf_dir), 4, init="column", start="start", **options)), _TRUTH)


for _n, _title in (("k1", "separate_buffered"), ("k2", "separate_indirect"), ("k3", "localized_indirect"), ("k4", "localized_buffered")):
    _settled(f"km_{_n}_{_title}", **K.PRESETS[_n])
_settled("km_master_exchange", **K.PRESETS["k5"])
_settled("km_range_shards", shards=8, split="range")
_settled("km_value_shards", shards=8, split="value")
for _n in ("separate_buffered", "separate_indirect", "localized_indirect", "localized_buffered"):
    _settled(f"km_rows_{_n}", **K.PRESETS[_n])
_settled("km_any_shards", shards=8, split="any")
_settled("km_block_shards", shards=4, split="block", layout="localized_blocks")
_settled("km_local_sweeps4_frozen", shards=4, sweeps_per_exchange=4, local="frozen")


def km_conservation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moves conserve the number of points and the coordinate sums."""
    c = K.kmeans(T.lineitem_started(spark, sf_dir), 4, init="column", start="start", stop=Stop.max_iter(3), max_sweeps=3).state["centers"]
    return c.agg(F.sum("n").alias("n"), *(F.round(F.sum(F.col(f"c{j}") * F.col("n")), 3).alias(f"s{j}") for j in range(4)))


_add("km_conservation", km_conservation, f"SELECT CAST(count(*) AS BIGINT) AS n, {', '.join(f'round(CAST(sum(x{j}) AS DOUBLE), 3) AS s{j}' for j in range(4))} FROM ({S.POINTS['exact']})")


def km_enabled_at_rest(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = T.anchored(spark, sf_dir)
    run = K.kmeans(p, 4, init="column", start="start")
    left = K.enabled_tuples(p, run.state["assign"], run.state["centers"])
    return left.join(run.state["assign"].groupBy("c").agg(F.count(F.lit(1)).alias("size")))  # one row by k


_add("km_enabled_at_rest", km_enabled_at_rest, f"SELECT CAST(0 AS BIGINT) AS enabled, truth AS c, CAST(count(*) AS BIGINT) AS size FROM ({S.POINTS['anchored']}) GROUP BY truth")


def km_assign_new(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centres of two sweeps, then the nearest of them for every point."""
    p = T.lineitem_started(spark, sf_dir)
    run = K.kmeans(p, 4, init="column", start="start", stop=Stop.max_iter(2), max_sweeps=2)
    return K.assign(p, run.state["centers"]).groupBy("c").agg(F.count(F.lit(1)).alias("n"))


_DS = ", ".join("(" + " + ".join(f"(x{j} - (SELECT s{j} / n FROM m2 WHERE m = {m})) * (x{j} - (SELECT s{j} / n FROM m2 WHERE m = {m}))" for j in range(4)) + f") AS d{m}" for m in range(4))
_add("km_assign_new", km_assign_new, f"{S.kmeans_chain(S.POINTS['started'], 4, 4, 2)} SELECT CAST(CASE WHEN d0 = b THEN 0 WHEN d1 = b THEN 1 WHEN d2 = b THEN 2 ELSE 3 END AS INT) AS c, CAST(count(*) AS BIGINT) AS n FROM (SELECT *, least(d0, d1, d2, d3) AS b FROM (SELECT *, {_DS} FROM ({S.POINTS['exact']}))) GROUP BY 1")


def km_sse_by_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    p = T.lineitem_started(spark, sf_dir).persist()
    for sweeps in (1, 2, 3):
        run = K.kmeans(p, 4, init="column", start="start", exchange="indirect", stop=Stop.max_iter(sweeps), max_sweeps=sweeps)
        row = K.sse(p, run.state["assign"], run.state["centers"]).select(F.lit(sweeps).alias("sweep"), F.round("sse", 2).alias("sse"))
        out = row if out is None else out.unionByName(row)
    return out


_SSE = " UNION ALL ".join(f"SELECT CAST({t} AS INT) AS sweep, round(sum({' + '.join(f'(x{j} - s{j} / n) * (x{j} - s{j} / n)' for j in range(4))}), 2) AS sse FROM a{t} JOIN m{t} ON c = m" for t in (1, 2, 3))
_add("km_sse_by_sweep", km_sse_by_sweep, f"{S.kmeans_chain(S.POINTS['started'], 4, 4, 3)} {_SSE}")


def km_stop_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which rule stops the anchored run, and when."""
    p = T.anchored(spark, sf_dir).persist()
    rules = [("center_shift", Stop.center_shift()), ("switch_fraction", Stop.switch_fraction()), ("max_iter", Stop.max_iter(1)), ("quiet", Stop.quiet())]
    rows = []
    for name, stop in rules:
        run = K.kmeans(p, 4, init="column", start="start", stop=stop)
        rows.append((name, run.reason, run.sweeps))
    return spark.createDataFrame(rows, "rule string, reason string, sweeps int")


_add("km_stop_rules", km_stop_rules, "SELECT * FROM (VALUES ('center_shift', 'quiet', CAST(2 AS INT)), ('switch_fraction', 'quiet', 2), ('max_iter', 'sweeps', 1), ('quiet', 'quiet', 2)) t(rule, reason, sweeps)")


def km_serial_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The move program tuple by tuple, with immediate exchange, on all nations (25 at every scale): sizes at rest."""
    truth = (F.col("n_regionkey") % 4).cast("int")
    points = T.table(spark, sf_dir, "nation").select((F.col("n_nationkey") + 1000 * truth).alias("x0"), F.when(F.col("n_nationkey") % 7 == 0, (truth + 1) % 4).otherwise(truth).alias("start"))
    c, _, _ = K.kmeans_serial([((r[0],), r[1]) for r in points.orderBy("x0").collect()], 4)
    return spark.createDataFrame([(int(x),) for x in c], "m int").groupBy("m").agg(F.count(F.lit(1)).alias("size"))


_add("km_serial_spec", km_serial_spec, "SELECT CAST(n_regionkey % 4 AS INT) AS m, CAST(count(*) AS BIGINT) AS size FROM nation GROUP BY 1")


def km_gaussian_generated(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = G.gen_gaussian(spark, 20_000).persist()
    return _centres(K.kmeans(p, 4, init="sample", stop=Stop.any(Stop.center_shift(), Stop.max_iter(10)), max_sweeps=10))


_add("km_gaussian_generated", km_gaussian_generated)


def km_outlier_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sweeps until the switched fraction is small, over 20 random starts, without a cap on sweeps; runs far above the median are marked."""
    return X.outlier_study(spark)


_add("km_outlier_study", km_outlier_study)
_add("km_library_quality", lambda spark, sf_dir: X.library_quality(spark, sf_dir))
for _n, _f in X.WORKLOADS.items():
    _add(_n, _f)

# ---- ranks


def _ranks(run, digits: int = 9) -> DataFrame:
    return run.state["ranks"].select("id", F.round("pr", digits).alias("pr"))


def _pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.number_vertices(T.page_names(spark, sf_dir))[0]


EDGES = {"trade": T.trade, "handover": T.handover, "transitions": T.transitions, "pages": _pages}


def _pr(name: str, graph: str, sweeps: int = SWEEPS, d: float = 0.85, **options) -> None:
    _add(name, lambda spark, sf_dir: _ranks(R.rank(EDGES[graph](spark, sf_dir), d=d, stop=Stop.max_iter(sweeps), max_sweeps=sweeps, **options)), S.rank_delta(graph, sweeps, d))


for _g in EDGES:
    _add(f"pr_classic_{_g}", lambda spark, sf_dir, g=_g: _ranks(R.rank_classic(EDGES[g](spark, sf_dir), max_iter=CLASSIC)), S.rank_classic(_g, CLASSIC))
    _pr(f"pr_delta_{_g}", _g)
    _add(f"pr_rest_{_g}", lambda spark, sf_dir, g=_g: _ranks(R.rank(EDGES[g](spark, sf_dir), variant="r4", stop=Stop.residual(1e-9), max_sweeps=400), 7), S.rank_classic(_g, REST, digits=7))
for _v in R.PRESETS:
    _pr(f"pr_{_v}", "trade" if _v in ("folded", "expanded", "r1", "r2", "r3", "r4") else "pages" if _v in ("edge_delta", "localized", "adjacency") else "transitions", variant=_v)
for _x in (0.5, 0.85, 0.95):
    _pr(f"pr_damping_{int(_x * 100)}", "transitions", d=_x)


def _invariant(name: str, **options) -> None:
    """Partial and stale schedules keep the invariant exactly and come to rest at the same ranks."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = T.transitions(spark, sf_dir)
        r = R.rank(e, stop=Stop.residual(1e-8), max_sweeps=600, **({"memory": "adjacency"} | options))
        gap = round(float(R.invariant_error(r, e)), 9) + 0.0
        return _ranks(r, 6).select("id", "pr", F.lit(gap).alias("gap"))

    _add(name, run, f"SELECT *, CAST(0.0 AS DOUBLE) AS gap FROM ({S.rank_classic('transitions', REST, digits=6)})")


_invariant("pr_half_schedule", schedule=Schedule.sample(0.5))
_invariant("pr_priority_schedule", schedule=Schedule.priority(0.5))
_invariant("pr_alternating_schedule", schedule=Schedule.alternating())
_invariant("pr_local_sweeps4", memory="adjacency", sweeps_per_exchange=4)


def pr_residual_by_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    run = R.rank(T.trade(spark, sf_dir), stop=Stop.max_iter(6), max_sweeps=6)
    return spark.createDataFrame([(i + 1, round(x["residual"], 9)) for i, x in enumerate(run.log)], "sweep int, residual double")


_add("pr_residual_by_sweep", pr_residual_by_sweep, S.rank_delta("trade", 6, select="SELECT CAST(sweep AS INT) AS sweep, round(sum(x), 9) AS residual FROM t WHERE sweep > 0 GROUP BY sweep"))


def pr_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    run = R.rank_classic(T.trade(spark, sf_dir), max_iter=6)
    return run.state["ranks"].agg(F.round(F.sum("pr"), 9).alias("mass"), F.count(F.lit(1)).alias("vertices"), F.round(F.max("pr"), 9).alias("largest"))


_add("pr_mass", pr_mass, f"SELECT round(sum(pr), 8) AS mass, count(*) AS vertices, max(pr) AS largest FROM ({S.rank_classic('trade', 6)})")


def pr_topn_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten pages of the largest ranks at rest."""
    edges, names = T.number_vertices(T.page_names(spark, sf_dir))
    r = _ranks(R.rank(edges, variant="r4", stop=Stop.residual(1e-9), max_sweeps=400), 7)
    return r.orderBy(F.desc("pr"), "id").limit(10).join(names, "id").select("name", "pr")


def pr_topn_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten traders of the largest ranks at rest, customers and suppliers by name."""
    r = _ranks(R.rank(T.trade(spark, sf_dir), variant="r4", stop=Stop.residual(1e-9), max_sweeps=400), 7)
    names = T.table(spark, sf_dir, "customer").select((F.col("c_custkey") * 2).alias("id"), F.col("c_name").alias("name"))
    names = names.unionByName(T.table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2 + 1).alias("id"), F.col("s_name").alias("name")))
    return r.orderBy(F.desc("pr"), "id").limit(10).join(names, "id").select("name", "pr")


_NAMES = f"(SELECT name, row_number() OVER (ORDER BY name) AS id FROM (SELECT a AS name FROM ({S.GRAPHS['names']}) UNION SELECT b FROM ({S.GRAPHS['names']})))"
_add("pr_topn_pages", pr_topn_pages, f"SELECT name, pr FROM (SELECT * FROM ({S.rank_classic('pages', REST, digits=7)}) ORDER BY pr DESC, id LIMIT 10) JOIN {_NAMES} USING (id)")
_TRADERS = "(SELECT c_custkey * 2 AS id, c_name AS name FROM customer UNION ALL SELECT s_suppkey * 2 + 1, s_name FROM supplier)"
_add("pr_topn_customers", pr_topn_customers, f"SELECT name, pr FROM (SELECT * FROM ({S.rank_classic('trade', REST, digits=7)}) ORDER BY pr DESC, id LIMIT 10) JOIN {_TRADERS} USING (id)")
_add("pr_kron_generated", lambda spark, sf_dir: _ranks(R.rank(G.gen_kron(spark, 12, 40_000), variant="r4", stop=Stop.residual(1e-8), max_sweeps=400)))
_add("pr_sampled_fold", lambda spark, sf_dir: _ranks(R.rank(_pages(spark, sf_dir), dangling="sample", stop=Stop.max_iter(4), max_sweeps=4)))

# ---- baselines

_add("baseline_km_mr", lambda spark, sf_dir: _centres(B.baseline_kmeans_mr(T.lineitem_started(spark, sf_dir), 4, delta=0.0, max_iter=3)), S.kmeans_centres(S.POINTS["started"], 4, 4, 3, "last"))
_add("baseline_km_bsp", lambda spark, sf_dir: _centres(B.baseline_kmeans_bsp(T.lineitem_started(spark, sf_dir), 4, theta=0.0, max_iter=3)), S.kmeans_centres(S.POINTS["started"], 4, 4, 3, "last"))
_add("baseline_rank_mr", lambda spark, sf_dir: _ranks(B.baseline_rank_mr(T.trade(spark, sf_dir), eps=0.0, max_iter=5)), S.rank_classic("trade", 5))
_add("baseline_rank_naive", lambda spark, sf_dir: _ranks(B.baseline_rank_naive(T.trade(spark, sf_dir), stop=Stop.max_iter(4), max_sweeps=4)), S.rank_delta("trade", 4))
_add("baseline_rank_bsp", lambda spark, sf_dir: _ranks(B.baseline_rank_bsp(T.trade(spark, sf_dir), max_iter=5)), S.rank_classic("trade", 5))

# ---- graphs

for _g in EDGES:
    _add(f"graph_{_g}_edges", lambda spark, sf_dir, g=_g: EDGES[g](spark, sf_dir), S.GRAPHS[_g])
_add("graph_degrees", lambda spark, sf_dir: T.degrees(T.trade(spark, sf_dir)), f"SELECT u, count(*) AS dout FROM ({S.GRAPHS['trade']}) GROUP BY u")
_add("graph_dangling", lambda spark, sf_dir: T.dangling(T.trade(spark, sf_dir)), f"WITH e AS ({S.GRAPHS['trade']}) SELECT DISTINCT v AS id FROM e WHERE v NOT IN (SELECT u FROM e)")
_add("shared_addresses", lambda spark, sf_dir: P.shared_addresses(T.transitions(spark, sf_dir), F.col("u") % 4), f"SELECT v AS address, count(DISTINCT u % 4) AS shards FROM ({S.GRAPHS['transitions']}) GROUP BY v HAVING count(DISTINCT u % 4) > 1")


def _cover(how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = T.transitions(spark, sf_dir).withColumn("s", P.shard_of(F.col("v"), 8, how, 0, 49))
        return e.groupBy("s").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("n"), F.max("s").alias("last")) if how == "range" else e.groupBy("s").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("n"))

    return run


_add("shard_cover_value", _cover("value"), f"SELECT CAST(count(*) AS BIGINT) AS n FROM ({S.GRAPHS['transitions']})")
_add("shard_cover_range", _cover("range"), f"SELECT CAST(count(*) AS BIGINT) AS n, CAST(max(least(7, floor(v / 6.125))) AS INT) AS last FROM ({S.GRAPHS['transitions']})")

def overlap_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Earliest in-neighbour of each bucket over shards that overlap; a minimum may see a tuple twice."""
    e = T.transitions(spark, sf_dir)
    return P.once_covered(e, P.covers(F.col("u"), 8, 0, 49, 3), ["v"], F.col("u"), "min")


_add("overlap_cover", overlap_cover, f"SELECT v, min(u) AS value FROM ({S.GRAPHS['transitions']}) GROUP BY v")

# ---- sparse products and sorting: part by supplier quantities of all lines

_A = "SELECT l_partkey AS i, l_suppkey AS j, CAST(sum(CAST(round(l_quantity) AS BIGINT)) AS BIGINT) AS val FROM lineitem GROUP BY 1, 2"


def _matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j")).agg(F.sum(F.round("l_quantity").cast("bigint")).alias("val"))


def mm_sparse_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers by suppliers, over the parts that both deliver: the transposed matrix times itself."""
    a = _matrix(spark, sf_dir)
    return P.matmul(a.select(F.col("j").alias("i"), F.col("i").alias("j"), "val"), a)


_add("mm_sparse_product", mm_sparse_product, f"WITH a AS ({_A}) SELECT a.j AS i, b.j AS j, CAST(sum(a.val * b.val) AS BIGINT) AS val FROM a JOIN a b ON a.i = b.i GROUP BY a.j, b.j")


def _product(layout: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        b = T.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("j"), F.lit(1).alias("c0"), F.col("s_nationkey").alias("c1"), F.round("s_acctbal").cast("bigint").alias("c2"))
        out = P.spmm(_matrix(spark, sf_dir), b, layout)
        return out.select("i", *(F.round(c).cast("bigint").alias(c) for c in ("c0", "c1", "c2")))

    return run


for _l, _n in (("coo", "mm_triples"), ("row_lists", "mm_row_lists"), ("padded", "mm_padded"), ("jagged", "mm_jagged")):
    _add(_n, _product(_l), f"WITH a AS ({_A}) SELECT i, CAST(sum(val) AS BIGINT) AS c0, CAST(sum(val * s_nationkey) AS BIGINT) AS c1, CAST(sum(val * CAST(round(s_acctbal) AS BIGINT)) AS BIGINT) AS c2 FROM a JOIN supplier ON j = s_suppkey GROUP BY i")
_add("mm_derived", lambda spark, sf_dir: _product(L.product_layout(L.diagonal_product("jagged")))(spark, sf_dir), ORACLES["mm_jagged"])
_add("mm_jagged_form", lambda spark, sf_dir: P.to_jagged(_matrix(spark, sf_dir)), f"WITH a AS ({_A}) SELECT CAST(count(*) OVER (PARTITION BY i) AS BIGINT) AS length, i, CAST(row_number() OVER (PARTITION BY i ORDER BY j) - 1 AS INT) AS kk, j, val FROM a")


def _slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All nations (25 at every scale) in an order that is not the one of their values."""
    return T.table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("slot"), ((F.col("n_nationkey") * 7 + F.col("n_regionkey") * 13) % 23).cast("long").alias("value"))


_SORTED = "SELECT CAST(row_number() OVER (ORDER BY value) - 1 AS BIGINT) AS slot, value FROM (SELECT CAST(round(c_acctbal) AS BIGINT) AS value FROM customer{where})"
_add("sort_builtin", lambda spark, sf_dir: P.sort_builtin(T.table(spark, sf_dir, "customer").select(F.round("c_acctbal").cast("long").alias("value"))), _SORTED.format(where=""))
_SLOTS = "SELECT CAST(row_number() OVER (ORDER BY value) - 1 AS BIGINT) AS slot, value FROM (SELECT CAST((n_nationkey * 7 + n_regionkey * 13) % 23 AS BIGINT) AS value FROM nation)"
_add("sort_neighbours", lambda spark, sf_dir: P.sort_neighbours(_slots(spark, sf_dir)), _SLOTS)
_add("sort_all_pairs", lambda spark, sf_dir: P.sort_all_pairs(_slots(spark, sf_dir)), _SLOTS)


def once_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return P.once(T.table(spark, sf_dir, "lineitem"), ["l_suppkey"], F.round("l_quantity").cast("bigint"))


_add("once_loop", once_loop, "SELECT l_suppkey, CAST(sum(CAST(round(l_quantity) AS BIGINT)) AS BIGINT) AS value FROM lineitem GROUP BY l_suppkey")


def derived_forms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Programs that legal chains of transformations lead to, with their cost per sweep on these tables."""
    e = T.trade(spark, sf_dir)
    stats = {"vertices": T.vertices_of(e).count(), "edges": e.count(), "dangling": T.dangling(e).count()}
    n = T.table(spark, sf_dir, "lineitem").count()
    rows = []
    for spec, s in ((L.rank_spec(), stats), (L.kmeans_spec(), {"points": n, "k": 4, "d": 4})):
        rows += [(spec.name, i, float(L.cost(x, s)), " > ".join(x.steps)) for i, x in enumerate(L.ranked(spec, s)[:20])]
    return spark.createDataFrame(rows, "program string, place int, bytes double, steps string")


_add("derived_forms", derived_forms)


def derived_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every different plan that the derivation leads to, run to the same sweep: how many forms, and their one answer."""
    e = T.transitions(spark, sf_dir).persist()
    seen, out = set(), None
    for spec in L.derive(L.rank_spec(), parts=4):
        options = L.rank_options(spec)
        key = (options["memory"], options["orientation"], options["dangling"], options["index"])
        if key in seen or options["dangling"] == "sample" or options["sweeps_per_exchange"] > 1:
            continue
        seen.add(key)
        got = R.rank(e, stop=Stop.max_iter(2), max_sweeps=2, **options).state["ranks"]
        out = got if out is None else out.unionByName(got)
    return out.groupBy("id").agg(F.round(F.min("pr"), 9).alias("low"), F.round(F.max("pr"), 9).alias("high"))


_add("derived_ranks", derived_ranks, f"SELECT id, pr AS low, pr AS high FROM ({S.rank_delta('transitions', 2)})")


def derived_kmeans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every different plan of the k-Means derivation, run to rest on the anchored points: the centres that all agree on.

    Points are read by each run and a run's states are released before the next, so that memory holds one run's tables.
    """
    p = T.anchored(spark, sf_dir)
    seen, out = set(), None
    for spec in L.derive(L.kmeans_spec(), parts=4):
        options = L.kmeans_options(spec)
        key = L.kmeans_plan(options)
        if key in seen:
            continue
        seen.add(key)
        run = K.kmeans(p, 4, init="column", start="start", **options)
        got = _centres(run)
        run.release()
        out = got if out is None else out.unionByName(got)
    return out.distinct()


_add("derived_kmeans", derived_kmeans, _TRUTH)

# ---- streams

_add("stream_windows", lambda spark, sf_dir: W.windowed_counts(W.event_stream(spark, sf_dir)), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY 1, 2")
_add(
    "stream_sessions", lambda spark, sf_dir: W.sessions(W.event_stream(spark, sf_dir)),
    "SELECT user_id, CAST(sum(new) AS BIGINT) AS sessions, CAST(count(*) AS BIGINT) AS events FROM (SELECT user_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) GROUP BY user_id",
)
_add("stream_first_seen", lambda spark, sf_dir: W.first_seen(W.event_stream(spark, sf_dir)), "SELECT DISTINCT user_id, event_type FROM events")


def stream_minibatch_km(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centres of a first pass take in streamed points: sizes and sums grow by all of them."""
    stream = W.event_stream(spark, sf_dir).select((F.floor("value") % 50).cast("bigint").alias("x0"), F.length("event_type").cast("bigint").alias("x1"))
    end = W.minibatch_kmeans(stream, {0: (1, [0, 8]), 1: (1, [49, 8])})
    return spark.createDataFrame([(sum(v[0] for v in end.values()) - 2, int(sum(v[1][0] for v in end.values())) - 49)], "n long, s0 long")


_add("stream_minibatch_km", stream_minibatch_km, "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(floor(value) AS BIGINT) % 50) AS BIGINT) AS s0 FROM events")


def stream_incremental_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = W.event_stream(spark, sf_dir).select((F.floor("value") % 50).cast("bigint").alias("u"), (F.col("user_id") % 50).alias("v"))
    known = spark.createDataFrame([(0, 1)], "u long, v long")
    return W.incremental_rank(stream, known).select("id", F.round("pr", 7).alias("pr"))


_EVENT_EDGES = "SELECT DISTINCT u, v FROM (SELECT CAST(floor(value) AS BIGINT) % 50 AS u, user_id % 50 AS v FROM events UNION ALL SELECT 0, 1)"
S.GRAPHS["event_edges"] = _EVENT_EDGES
_add("stream_incremental_rank", stream_incremental_rank, S.rank_classic("event_edges", REST, digits=7))
