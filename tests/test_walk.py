"""The method against its own laws: worked values, conservation, equalities, distributions."""

import math
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng
from walkrank.operators import accuracy, baselines, cost, erasure, prepare, theory, walk
from walkrank.sources import graphs

GOLD = {
    1: (0.35625, 0.14375, 0.4625, 0.0375), 2: (0.4465625, 0.18890625, 0.32703125, 0.0375),
    3: (0.3314140625, 0.2272890625, 0.403796875, 0.0375), 4: (0.3966648437, 0.1783509766, 0.3874841797, 0.0375),
}
FIXED = (0.3797343132, 0.1988870831, 0.3838786037, 0.0375)


def values(df):
    return [r.value for r in df.orderBy("id").collect()]


def params(**more):
    return walk.WalkParams(**({"n_walkers": 2000, "horizon": 4} | more))


@pytest.fixture(scope="module")
def toy(spark):
    return graphs.toy(spark)


@pytest.fixture(scope="module")
def random_edges(spark):
    rng = np.random.default_rng(0)
    pairs = {(f"n{a}", f"n{b}") for a, b in rng.zipf(1.5, (1500, 2)) % 60 if a % 60 != b % 60}
    pairs |= {(f"n{i}", f"n{(i + 1) % 60}") for i in range(60)}
    return spark.createDataFrame(sorted(pairs), "src string, dst string").cache()


@pytest.mark.parametrize("t", GOLD)
def test_worked_example(toy, t):
    assert np.allclose(values(baselines.fixed(toy, t)), GOLD[t], atol=1e-9)
    assert np.allclose(values(baselines.series(toy, t)), GOLD[t], atol=1e-9)


def test_fixed_point_and_dense_solution(toy):
    a = np.zeros((4, 4))
    for s, d in graphs.TOY:
        a["abcd".index(d), "abcd".index(s)] = 1
    p = a / a.sum(axis=0)
    dense = np.linalg.solve(np.eye(4) - 0.85 * p, np.full(4, 0.15 / 4))
    rank, n = baselines.tolerance(toy, 1e-10)
    assert np.allclose(values(rank), dense, atol=1e-9) and np.allclose(dense, FIXED, atol=1e-9) and n > 40
    sent, _ = baselines.delta(toy, 1e-9)
    assert np.allclose(values(sent), dense, atol=1e-7)


def test_exact_takes_few_iterations(spark):
    pairs = np.random.default_rng(0).integers(0, 90, (2400, 2))
    rows = sorted({(f"n{a:02}", f"n{b:02}") for a, b in pairs if a != b and a < 84} | {(f"n{i:02}", f"n{i:02}") for i in range(84, 90)})
    p = np.zeros((90, 90))
    for s, d in rows:
        p[int(d[1:]), int(s[1:])] = 1
    dense = np.linalg.solve(np.eye(90) - 0.85 * p / p.sum(axis=0), np.full(90, 0.15 / 90))
    edges = spark.createDataFrame(rows, "src string, dst string")
    assert np.allclose(values(baselines.exact(edges, most=40)), dense, atol=1e-12, rtol=0)  # power iteration takes about 170
    assert baselines.exact(edges.limit(0)).count() == 0
    assert np.allclose(baselines.least_mean(np.diag([4.0, 1.0])), [0.2, 0.8]) and list(baselines.least_mean(np.zeros((2, 2)))) == [0, 1]


def test_top_one_of_two_iterations_is_not_the_best(toy):
    ref = baselines.fixed(toy, 60)
    est = baselines.fixed(toy, 2)
    assert accuracy.identified(est, ref, 1).first().hits == 0
    assert accuracy.mass_captured(est, ref, 1, True).first().mass == pytest.approx(0.98921, abs=1e-4)
    assert accuracy.mass_captured(est, ref, 0).first().mass == 0
    assert accuracy.mass_captured(ref, ref, 9, True).first().mass == pytest.approx(1)


@pytest.mark.parametrize("more", [{}, {"refresh_rate": 0.4}, {"refresh_rate": 0.4, "rounding": "exact"}, {"refresh_rate": 0.1, "replica_weight": "degree"}, {"refresh_rate": 0.4, "erasure": "independent", "rounding": "exact"},
                                  {"refresh_rate": 0.3, "erasure": "independent", "on_no_live": "stay", "rounding": "exact"}, {"refresh_rate": 0.3, "erasure": "independent", "on_no_live": "stop_here", "rounding": "exact"}])
def test_conservation(random_edges, more):
    lay = prepare.layout(random_edges, "random", 4)
    got = walk.walker_tally(lay, params(n_walkers=500, horizon=3, **more))
    total = got.tally.agg(F.sum("c")).first()[0]
    if more.get("rounding") == "exact" or more.get("replica_weight") == "degree":
        assert total <= 500 if more.get("erasure") == "independent" and "on_no_live" not in more else total == 500
    else:
        assert total >= 500
    for s in got.steps:
        assert s["refresh_sent"] <= s["refresh_tried"] and s["alive_out"] >= 0
    assert cost.walker_model_bytes(got.steps) > 0


def test_long_walks_end_and_lose_nobody(spark):
    lay = prepare.layout(graphs.toy(spark), "random", 3, Rng(3))
    p = walk.WalkParams(n_walkers=40, horizon=None, stop_rate=0.5, refresh_rate=0.5, rounding="exact", max_steps=30, rng=Rng(3))
    one, two = walk.walker_tally(lay, p), walk.walker_tally(lay, walk.with_params(p, counters=False))
    got = sorted(map(tuple, one.tally.collect()))
    assert got == sorted(map(tuple, two.tally.collect())) and sum(c for _, c in got) == 40
    assert one.steps[-1]["alive_out"] == 0 and sum(s["stopped"] for s in one.steps) == 40 and len(one.steps) < 30


def test_fewer_refreshes_cost_less(random_edges):
    lay = prepare.layout(random_edges, "random", 8)
    sent = {p: sum(s["refresh_sent"] for s in walk.walker_tally(lay, params(refresh_rate=p)).steps) for p in (1.0, 0.7, 0.4, 0.1)}
    assert sent[1.0] > sent[0.7] > sent[0.4] > sent[0.1]


def test_partitions_do_not_matter(random_edges):
    one = walk.walker_tally(prepare.layout(random_edges.coalesce(1)), params(refresh_rate=0.4, counters=False)).tally
    two = walk.walker_tally(prepare.layout(random_edges.repartition(9)), params(refresh_rate=0.4, counters=False)).tally
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect()))


def test_runner_equals_direct_form(random_edges):
    lay = prepare.layout(random_edges)
    p = params(n_walkers=800, horizon=2, refresh_rate=0.7, counters=False)
    assert sorted(map(tuple, walk.run(walk.walker_program(p), lay, 2).collect())) == sorted(map(tuple, walk.walker_tally(lay, p).tally.collect()))


def test_walkers_follow_the_law(toy):
    """Chi-square of the tally against the law of where a walker stops, for all kinds of walk."""
    n = 20000
    laws = dict(zip("abcd", GOLD[3]))
    lay = prepare.layout(toy, "source", 2)
    teleported = baselines.fixed(toy, 3)
    for tally in (
        walk.walker_tally(lay, params(n_walkers=n, horizon=3, counters=False, rng=Rng(3, "fast"))).tally,
        walk.identity_walk(toy, n, 3, 0.15, 1.0, Rng(4, "fast")).where("stopped").groupBy("id").agg(F.count("*").alias("c")),
        walk.teleport_walk(toy, n, 3, 0.15, Rng(5, "fast")),
    ):
        got = {r.id: r.c for r in tally.collect()}
        assert sum((got.get(v, 0) - n * q) ** 2 / (n * q) for v, q in laws.items()) < 25  # 3 degrees of freedom
    assert np.allclose(values(teleported), list(laws.values()))


def test_blocking_walk_moves_as_the_live_one(toy):
    n = 20000
    runs = {h: walk.identity_walk(toy, n, 2, 0.15, 0.5, Rng(9, "fast"), h).where("stopped") for h in ("serial", "live", "blocking")}
    c = {h: {r.id: r["count"] for r in d.groupBy("id").count().collect()} for h, d in runs.items()}
    assert all(abs(c["serial"].get(v, 0) / n - q) < 0.02 for v, q in zip("abcd", GOLD[2]))
    assert walk.identity_walk(toy, 500, 2, 0.15, 1.0, Rng(9, "fast"), "blocking").where("blocked").isEmpty()
    assert not runs["blocking"].where("blocked").isEmpty()


@pytest.mark.parametrize("d,p,a,block", [(1, 0.5, 1, 1), (2, 0.5, 0.625, 0.4375), (3, 0.1, 0.343, 0.121), (5, 0.4, 0.41555, 0.21111)])
def test_erasure_closed_forms(spark, d, p, a, block):
    row = spark.range(1).select(erasure.live_probability(F.lit(float(d)), p).alias("a"), erasure.no_block_probability(F.lit(float(d)), p).alias("b")).first()
    assert row.a == pytest.approx(a, abs=1e-4) and row.b == pytest.approx(block, abs=1e-4) and block >= p * p
    live = 0.0
    for s in product((0, 1), repeat=d):
        q = math.prod(p if x else 1 - p for x in s)
        live += q * (s[0] if any(s) else 1 / d)
    assert live == pytest.approx(a, abs=1e-4)


def test_erasures_keep_one_edge(random_edges):
    kept = erasure.at_least_one(random_edges, 0.05, 1)
    assert kept.select("src").distinct().count() == random_edges.select("src").distinct().count()
    assert kept.count() < random_edges.count() / 2 and kept.join(random_edges, ["src", "dst"], "left_anti").isEmpty()
    audit = {r.property: r for r in erasure.audit(graphs.toy(random_edges.sparkSession), 0.5, 40).collect()}
    assert audit["keep"].ok and audit["source"].observed is not None and abs(audit["step"].observed) < 0.3


def test_split_rules(spark):
    live = spark.sql("SELECT 'v' AS src, 5L AS k, 3 AS d_out, array(named_struct('shard', 0, 'd_local', 1), named_struct('shard', 1, 'd_local', 3), named_struct('shard', 2, 'd_local', 1)) AS reps")
    shares = lambda **m: sorted((r.k for r in walk.split_shares(None, live, 0, Rng(), **m).collect()), reverse=True)
    assert shares() == [2, 2, 2] and shares(rounding="exact") == [2, 2, 1] and shares(weight="degree") == [3, 1, 1]
    few = live.withColumn("k", F.lit(2).cast("long"))
    assert sorted(r.k for r in walk.split_shares(None, few, 0, Rng()).collect()) == [1, 1]


def test_repair(spark):
    chain = spark.createDataFrame([("a", "b"), ("b", "a"), ("b", "c"), ("c", "d")], "src string, dst string")
    edges = lambda p: sorted(map(tuple, prepare.repair(chain, p).collect()))
    assert ("d", "d") in edges("self_loop") and ("d", "c") in edges("reverse_edge") and edges("drop") == [("a", "b"), ("b", "a")]
    with pytest.raises(ValueError):
        prepare.repair(chain, "reject")
    empty = chain.limit(0)
    assert prepare.repair(empty).count() == 0 and baselines.fixed(empty, 2).count() == 0


def test_layouts_hold_every_edge(random_edges):
    want = sorted(map(tuple, random_edges.collect()))
    for kind in ("random", "grid", "source", "chunked"):
        lay = prepare.layout(random_edges, kind, 6, chunk=4)
        assert sorted((r.src, v) for r in lay.replicas.collect() for v in r.nbrs) == want
        f = lay.replication().first()[0]
        assert f == 1 if kind == "source" else f > 1


def test_random_layout_of_a_hub_has_the_shards_asked_for(spark):
    hub = spark.range(20_000).select(F.lit("hub").alias("src"), F.concat(F.lit("n"), F.col("id")).alias("dst"))
    shards = lambda kind: {r.shard for r in prepare.shard_of(kind, 3, Rng())(hub).select("shard").distinct().collect()}
    assert shards("random") == {0, 1, 2} and shards("spread") == {0, 1, 2, 3, 4}  # 4096 neighbours a replica


def test_bounds():
    for t, want in ((3, 1.865), (4, 1.720), (10, 1.056), (11, 0.974), (40, 0.092)):
        assert theory.mixing(0.15, t) == pytest.approx(want, abs=1e-3)
    assert theory.total(0.15, 4, 10, 0.1, 1000, 1.0, 0.5) == pytest.approx(theory.mixing(0.15, 4) + math.sqrt(0.1))
    assert theory.plan_walkers(0.1, 100) == (3, 10000) and theory.chernoff_samples(0.01, 0.1, 0.05) > 1e4
    assert theory.power_law(10**6) == pytest.approx(10 ** (6 * (0.5 - 1 / 1.2)))
    assert theory.second_moment(100, 1.0, 0.3) == 0.01 and theory.tail(100, 1.0, 0.3, 0.5) == pytest.approx(0.04) and theory.interference(1.0, 0.3) == 0


def test_diagnostics(random_edges):
    n = prepare.vertices(random_edges).count()
    rank = baselines.fixed(random_edges, 40)
    assert theory.floor_ceiling(rank, n).first().floor_ok
    top = rank.agg(F.max("value")).first()[0]
    mass = theory.meeting_mass(random_edges, 4).orderBy("step").collect()[-1].cumulative
    pos = walk.identity_walk(random_edges, 2000, 4, 0.15, 1.0, Rng(2, "fast"))
    met = theory.met(pos).count() / 1000
    assert met <= mass * 1.3 + 0.05 and mass <= 5 * theory.meeting(n, 4, top, 0.15)
    assert all(r.ratio is None or r.ratio <= 0.85 + 1e-9 for r in theory.contraction(random_edges, 5).collect())
    assert accuracy.loss_chain(baselines.fixed(random_edges, 1), rank, 5).first().ok and theory.set_mass_gap(baselines.fixed(random_edges, 1), rank, 5).first().ok
    for r in theory.step_lengths(pos, 2000, 4).collect():
        assert abs(r.stopped - r.expected) < 5 * math.sqrt(r.expected)


def test_binomial_scatter_is_right_on_average(random_edges):
    lay = prepare.layout(random_edges, "random", 4)
    got = walk.walker_tally(lay, params(n_walkers=4000, horizon=2, refresh_rate=0.6, scatter="binomial_unbiased")).tally.agg(F.sum("c")).first()[0]
    assert 3000 < got < 5200
    born = walk.birth_per_vertex(lay.vertices, 6000, Rng(), lay.n).agg(F.sum("k")).first()[0]
    assert abs(born - 6000) < 5 * math.sqrt(6000)


def test_more_walkers_are_better_and_sparsified_is_worse(random_edges):
    lay = prepare.layout(random_edges, "random", 4)
    ref = baselines.fixed(random_edges, 40).cache()
    l1 = {n: accuracy.distance(walk.estimate(walk.walker_tally(lay, params(n_walkers=n, horizon=6, counters=False)).tally, n, "total"), ref).first().l1 for n in (200, 20000)}
    assert l1[20000] < l1[200] / 2
    s = {r: accuracy.distance(baselines.sparsified_rank(random_edges, r, 4), ref).first().l1 for r in (0.1, 0.7)}
    assert s[0.1] < s[0.7]
    r = accuracy.curve(baselines.in_degree(random_edges), ref, [1, 5, 20]).orderBy("k").collect()
    assert all(0 < x.mass_norm <= 1 + 1e-12 and x.hits <= x.k for x in r)
    assert accuracy.rank_corr(ref, ref, 10).first().spearman == pytest.approx(1)


def test_plans(random_edges):
    lay = prepare.layout(random_edges)
    live = erasure.live_replicas(lay.directory, 0.4, 0)
    plan = live._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan
    shares = walk.split_shares(None, live.withColumn("k", F.lit(3).cast("long")), 0, Rng())
    assert "Exchange" not in shares._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in walk.pick_in_replica(shares, lay.replicas, 0, Rng())._jdf.queryExecution().executedPlan().toString()
    gone = baselines.sparsified(random_edges, 0.5).join(random_edges.groupBy("src").count(), "src")
    assert "CartesianProduct" not in gone._jdf.queryExecution().executedPlan().toString()
