"""Hand-checked fractions, invariants and equality of all forms."""

import random

import pytest
from pyspark.sql import functions as F

from quiesce.functions import measures as Q
from quiesce.operators import rank as R
from quiesce.plans.policy import Schedule, Stop
from quiesce.sources import tables as T

TRI = [(1, 2), (1, 3), (2, 3)]


@pytest.fixture(scope="module")
def tri(spark):
    return spark.createDataFrame(TRI, "u long, v long").persist()


def ranks(run):
    return {r.id: r.pr for r in run.state["ranks"].collect()}


@pytest.mark.parametrize("variant", ["vertex_delta", "edge_delta", "materialized", "pull_shards", "pull_local_shards", "r1", "r4"])
def test_two_sweeps_by_hand(tri, variant):
    got = ranks(R.rank(tri, variant=variant, stop=Stop.max_iter(2), max_sweeps=2))
    for i, want in ((1, 3147 / 32000), (2, 1029 / 8000), (3, 1017 / 6400)):
        assert got[i] == pytest.approx(want, abs=1e-12)


def test_presets_differ():
    seen = [tuple(sorted((k, str(v)) for k, v in o.items())) for o in R.PRESETS.values()]
    assert len(set(seen)) == len(seen)


def test_packed_form_to_rest_and_from_known_ranks(spark):
    rng = random.Random(5)
    pairs = sorted({(rng.randrange(30), rng.randrange(40)) for _ in range(150)})
    e = spark.createDataFrame(pairs, "u long, v long")
    want = R.rank_exact(pairs, sorted({x for p in pairs for x in p}))
    run = R.rank(e, variant="r4", stop=Stop.residual(1e-8), max_sweeps=400)
    assert ranks(run) == pytest.approx(want, abs=1e-7) and R.invariant_error(run, e) < 1e-12
    more = e.unionByName(spark.createDataFrame([(3, 39), (41, 2)], "u long, v long"))
    again = R.rank(more, memory="adjacency", known=run.state["ranks"], stop=Stop.residual(1e-8), max_sweeps=400)
    both = sorted({*pairs, (3, 39), (41, 2)})
    assert ranks(again) == pytest.approx(R.rank_exact(both, sorted({x for p in both for x in p})), abs=1e-7)
    for options in ({"orientation": "push"}, {"sweeps_per_exchange": 3}):
        assert ranks(R.rank(e, memory="adjacency", stop=Stop.residual(1e-6), max_sweeps=400, **options)) == pytest.approx(want, abs=1e-5)
    with pytest.raises(ValueError, match="replicate"):
        R.rank(e, memory="adjacency", broadcast_bytes=0, sweeps_per_exchange=2)


def test_fixpoint_exact_and_serial_orders():
    want = R.rank_exact(TRI, [1, 2, 3])
    assert want[3] == pytest.approx(0.43274854, abs=1e-8) and sum(want.values()) == pytest.approx(1)
    for seed in range(5):
        rng = random.Random(seed)
        got = R.rank_serial(TRI, [1, 2, 3], order=lambda n, rng=rng: rng.sample(range(n), n))
        assert all(abs(got[i] - want[i]) < 1e-9 for i in want)


def test_leak_loses_rank():
    assert sum(R.rank_exact(TRI, [1, 2, 3], dangling="leak").values()) == pytest.approx(0.2530625)


def test_serial_pass_by_hand():
    got = R.rank_serial(TRI, [1, 2, 3], passes=1)
    assert [got[i] for i in (1, 2, 3)] == pytest.approx([67853 / 640000, 81453 / 640000, 2109 / 16000])


def test_residual_falls_by_d_and_bounds_the_error(tri):
    run = R.rank(tri, stop=Stop.max_iter(8), max_sweeps=8)
    res = [x["residual"] for x in run.log]
    assert all(b == pytest.approx(0.85 * a) for a, b in zip(res, res[1:]))
    exact = R.rank_exact(TRI, [1, 2, 3])
    assert sum(abs(exact[i] - p) for i, p in ranks(run).items()) <= 0.85 / 0.15 * res[-1] + 1e-12
    assert R.invariant_error(run, tri) < 1e-12
    assert run.metrics.count() == 8


@pytest.mark.parametrize("options", [{"schedule": Schedule.sample(0.5)}, {"schedule": Schedule.priority(0.5)}, {"memory": "edge", "schedule": Schedule.alternating()}, {"memory": "adjacency", "sweeps_per_exchange": 3}, {"memory": "adjacency", "schedule": Schedule.priority(0.5)}])
def test_any_schedule_keeps_the_invariant(spark, options):
    e = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (1, 3), (3, 3)], "u long, v long")
    run = R.rank(e, stop=Stop.max_iter(5), max_sweeps=5, **options)
    assert R.invariant_error(run, e) < 1e-12
    assert run.log[-1]["residual"] < run.log[0]["residual"]


def test_edge_cases(spark):
    cycle = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (1, 2)], "u long, v long")
    assert all(p == pytest.approx(1 / 3) for p in ranks(R.rank_classic(cycle, max_iter=3)).values())
    lone = spark.createDataFrame([(1,), (2,), (3,), (9,)], "id long")
    got = ranks(R.rank(cycle, lone, stop=Stop.max_iter(2), max_sweeps=2))
    assert set(got) == {1, 2, 3, 9}
    with pytest.raises(ValueError):
        R.rank(cycle, d=1.0)
    with pytest.raises(ValueError):
        R.rank(spark.createDataFrame([(1, None)], "u long, v long"))


def test_expansion_is_refused_beyond_the_limit(tri, monkeypatch):
    monkeypatch.setattr(R, "EXPANDED_LIMIT", 1)
    with pytest.raises(ValueError, match="fold"):
        R.rank(tri, dangling="expand")


@pytest.mark.parametrize("variant", ["expanded", "edge_delta", "pull_local_shards", "adjacency"])
def test_presets_group_the_added_edges_beyond_the_limit(spark, monkeypatch, variant):
    """More added edges than rows are allowed: none is left out, the ranks are those of all of them."""
    e = spark.createDataFrame([(1, 2), (1, 3), (2, 3), (2, 5), (4, 6), (4, 1)], "u long, v long")
    options = {"variant": variant, "stop": Stop.max_iter(3), "max_sweeps": 3}
    want = R.rank(e, **options)
    assert want.state["edges"].count() == 6 + 3 * 5
    monkeypatch.setattr(R, "EXPANDED_LIMIT", 14)
    got = R.rank(e, **options)
    assert got.state["edges"].count() == 6 and ranks(got) == pytest.approx(ranks(want), abs=1e-12)


def test_plain_assignment_breaks_the_invariant():
    """Assigning instead of adding forgets earlier in-edges."""
    pr, old = dict.fromkeys((1, 2, 3), 0.05), {}
    edges, dout = TRI + [(3, 1), (3, 2)], {1: 2, 2: 1, 3: 2}
    for u, v in edges:
        pr[v] = pr[v] * 0 + 0.85 * (pr[u] - old.get((u, v), 0.0)) / dout[u]
        old[u, v] = pr[u]
    gap = max(abs(pr[w] - 0.05 - 0.85 * sum(old[u, v] / dout[u] for u, v in edges if v == w)) for w in pr)
    assert gap > 0.01


def test_plan_has_no_cartesian_product_and_shuffles_past_the_broadcast_bound(tri):
    run = R.rank(tri, broadcast_bytes=0, stop=Stop.max_iter(1), max_sweeps=1)
    plan = run.state["ranks"]._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan
    assert ranks(run) == pytest.approx(ranks(R.rank(tri, stop=Stop.max_iter(1), max_sweeps=1)))


def test_numbering_and_measures(spark):
    edges, names = T.number_vertices(spark.createDataFrame([("a", "b"), ("c", "a")], "a string, b string"))
    assert sorted((r.id, r.name) for r in names.collect()) == [(1, "a"), (2, "b"), (3, "c")]
    assert sorted(map(tuple, edges.collect())) == [(1, 2), (3, 1)]
    a = spark.createDataFrame([(1, 0.5), (2, 0.3), (3, 0.2)], "id long, pr double")
    assert Q.l1(a, a).first()["l1"] == 0 and Q.topn_overlap(a, a, 2) == 1 and Q.kendall(a, a) == 1
    assert Q.mass(a).first()[0] == pytest.approx(1)
    t = spark.createDataFrame([("x", 1, 2.0), ("y", 1, 1.0)], "variant string, size int, secs double")
    assert {r.variant: r.speedup for r in Q.speedup(t, "x").collect()} == {"x": 1.0, "y": 2.0}
    assert Q.growth(t.withColumn("n", F.lit(1)), "n").count() == 2
