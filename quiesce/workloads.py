"""Experiment workloads as runs with a result table: sizes, dimensions, cluster counts, outliers, quality and memory.

Every table says what was run, for how many sweeps and how long a sweep took; ratios
come from ``functions.measures``. Generated points and graphs stand for the sizes of the
published runs, scaled down; callers choose larger ones.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import measures as Q
from .operators import baselines as B
from .operators import kmeans as K
from .operators import rank as R
from .plans.policy import Stop
from .sources import generators as G
from .sources import tables as T

_TIMES = "workload string, variant string, size long, parameter int, sweeps int, secs double, exchanged_bytes double, sse double"


def _row(workload: str, variant: str, size: int, parameter: int, run, spent: float) -> tuple:
    sent = [x["exchanged_bytes"] for x in run.log if "exchanged_bytes" in x]
    sse = [x["sse"] for x in run.log if x.get("sse") is not None]
    return workload, variant, size, parameter, run.sweeps, spent, float(sum(sent)) if sent else None, float(sse[-1]) if sse else None


def _timed(f) -> tuple[object, float]:
    began = time.perf_counter()
    out = f()
    return out, time.perf_counter() - began


def kmeans_sizes(spark: SparkSession, sizes: tuple[int, ...] = (1 << 12, 1 << 15), sweeps: int = 4, k: int = 4, variants: tuple[str, ...] = ("k1", "k2", "k3", "k4")) -> DataFrame:
    """Calculation time of variants and both baselines by number of generated points; nothing is read or written inside."""
    rows = []
    stop = Stop.any(Stop.center_shift(1e-4), Stop.max_iter(sweeps))
    for n in sizes:
        p = K.initial(G.gen_gaussian(spark, n, k=k), k).withColumnRenamed("c", "start").persist()
        p.count()
        runs = {v: lambda v=v: K.kmeans(p, k, init="column", start="start", stop=stop, max_sweeps=sweeps, **K.PRESETS[v]) for v in variants}
        runs |= {"map_reduce": lambda: B.baseline_kmeans_mr(p, k, max_iter=sweeps), "bulk": lambda: B.baseline_kmeans_bsp(p, k, max_iter=sweeps)}
        for name, f in runs.items():
            run, spent = _timed(f)
            rows.append(_row("kmeans_sizes", name, n, k, run, spent))
        p.unpersist()
    return spark.createDataFrame(rows, _TIMES)


def kmeans_dimensions(spark: SparkSession, dims: tuple[int, ...] = (4, 8, 16, 32, 64), n: int = 1 << 14, sweeps: int = 3) -> DataFrame:
    """Time of a run by dimension."""
    rows = []
    for d in dims:
        p = K.initial(G.gen_gaussian(spark, n, d=d), 4).withColumnRenamed("c", "start").persist()
        p.count()
        run, spent = _timed(lambda p=p: K.kmeans(p, 4, init="column", start="start", stop=Stop.max_iter(sweeps), max_sweeps=sweeps, **K.PRESETS["k4"]))
        rows.append(_row("kmeans_dimensions", "k4", n, d, run, spent))
        p.unpersist()
    return spark.createDataFrame(rows, _TIMES)


def kmeans_clusters(spark: SparkSession, ks: tuple[int, ...] = (2, 4, 8, 16, 32), n: int = 1 << 14, sweeps: int = 3) -> DataFrame:
    """Time of a run by number of clusters; messages grow with k (d + 1), not with points."""
    rows = []
    for k in ks:
        p = K.initial(G.gen_gaussian(spark, n, k=k), k).withColumnRenamed("c", "start").persist()
        p.count()
        run, spent = _timed(lambda p=p, k=k: K.kmeans(p, k, init="column", start="start", stop=Stop.max_iter(sweeps), max_sweeps=sweeps, **K.PRESETS["k4"]))
        rows.append(_row("kmeans_clusters", "k4", n, k, run, spent))
        p.unpersist()
    return spark.createDataFrame(rows, _TIMES)


def rank_sizes(spark: SparkSession, levels: tuple[int, ...] = (8, 10), sweeps: int = 3, variants: tuple[str, ...] = ("r1", "r2", "r3", "r4"), naive_limit: int = 1 << 20) -> DataFrame:
    """Time of variants and baselines by number of vertices of a generated graph; the first form is left out where its added edges exceed a limit."""
    rows = []
    for level in levels:
        e = G.gen_kron(spark, level, 16 << level).persist()
        n, stubs = T.vertices_of(e).count(), T.dangling(e).count()
        stop = Stop.max_iter(sweeps)
        runs = {v: lambda v=v, e=e: R.rank(e, variant=v, stop=stop, max_sweeps=sweeps) for v in variants}
        runs |= {"map_reduce": lambda e=e: B.baseline_rank_mr(e, max_iter=sweeps, eps=0.0), "bulk": lambda e=e: B.baseline_rank_bsp(e, max_iter=sweeps)}
        if stubs * n <= naive_limit:
            runs["naive"] = lambda e=e: B.baseline_rank_naive(e, stop=stop, max_sweeps=sweeps)
        for name, f in runs.items():
            run, spent = _timed(f)
            rows.append(_row("rank_sizes", name, n, level, run, spent))
        e.unpersist()
    return spark.createDataFrame(rows, _TIMES)


def speedups(times: DataFrame, baseline: str) -> DataFrame:
    return Q.speedup(times.select("variant", "size", "secs"), baseline)


def outlier_study(spark: SparkSession, seeds: int = 20, n: int = 2_000, theta: float = 1e-4) -> DataFrame:
    """seed, sweeps, sse, outlier: random starts under the threshold stop, run as long as they take."""
    p = G.gen_gaussian(spark, n).persist()
    rows = []
    for s in range(seeds):
        run = K.kmeans(p, 4, init="random_assign", seed=s, layout="localized_blocks", exchange="indirect", stop=Stop.switch_fraction(theta))
        rows.append(("k3", s, run.sweeps))
    p.unpersist()
    return Q.outliers(spark.createDataFrame(rows, "variant string, seed int, sweeps int")).select("seed", "sweeps", "median", "outlier")


def library_quality(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """variant, sse: the platform's own clustering and ours from sampled centres, on customers' activity."""
    p = T.customer_activity(spark, sf_dir, k).persist()
    own = K.kmeans(p, k, init="sample", stop=Stop.any(Stop.center_shift(1e-4), Stop.max_iter(30)), **K.PRESETS["k4"])
    library = B.baseline_kmeans_library(p, k)
    rows = [K.sse(p, run.state["assign"], run.state["centers"]).select(F.lit(name).alias("variant"), "sse") for name, run in (("k4", own), ("library", library))]
    return rows[0].unionByName(rows[1])


def memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """form, rows, bytes: what each form of the rank program keeps for the trade graph, measured on its cached tables.

    The expanded form is counted, not built: it holds a row for each added edge.
    """
    e = T.trade(spark, sf_dir).persist()
    n, m, stubs = T.vertices_of(e).count(), e.count(), T.dangling(e).count()
    out = []
    for form, options in (("r1", R.PRESETS["r1"]), ("r2", R.PRESETS["r2"]), ("r4", R.PRESETS["r4"])):
        run = R.rank(e, stop=Stop.max_iter(1), max_sweeps=1, **options)
        kept = run.state["edges"].persist()
        rows = kept.count()
        out.append((form, rows, Q.cached_bytes(kept)))
        kept.unpersist()
    row = out[0][2] / max(1, out[0][1])
    out.append(("expanded", m + stubs * (n - 1), int(row * (m + stubs * (n - 1)))))
    return spark.createDataFrame(out, "form string, rows long, bytes long")


WORKLOADS = {
    "work_kmeans_sizes": lambda spark, sf_dir: kmeans_sizes(spark), "work_kmeans_dimensions": lambda spark, sf_dir: kmeans_dimensions(spark), "work_kmeans_clusters": lambda spark, sf_dir: kmeans_clusters(spark),
    "work_rank_sizes": lambda spark, sf_dir: rank_sizes(spark), "work_memory": memory,
}
