"""Queries of the method, its variants, baselines and measures, each with its DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkrank.functions.rng import PartRng, Rng
from walkrank.functions.session import cut, read
from walkrank.operators import accuracy, baselines, cost, erasure, prepare, theory, walk
from walkrank.plans import oracle as o
from walkrank.sources import graphs

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}
RNG = Rng()
N, T = 2000, 4


def case(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f
    return put


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "toy":
        return graphs.toy(spark)
    if name == "words_w3":
        return graphs.words(spark, sf_dir, window=3)
    if name.startswith("words_"):
        return graphs.words(spark, sf_dir, lang=name[6:])
    return getattr(graphs, name)(spark, sf_dir)


def repaired(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return cut(prepare.repair(cut(graph(spark, sf_dir, name))))


def placed(spark: SparkSession, sf_dir: str, name: str, kind: str = "random", shards: int = 8, chunk: int = 16) -> prepare.Layout:
    return prepare.layout(repaired(spark, sf_dir, name), kind, shards, RNG, **({"chunk": chunk} if kind == "chunked" else {}))


_references: dict[tuple, DataFrame] = {}


def reference(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The converged rank vector of the repaired graph, computed once an application."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _references:
        rank = baselines.converged(graphs.trade_codes(spark, sf_dir), once=True, stay=True) if name == "trade" else None  # its edges are never held as text
        _references[key] = cut(baselines.exact(repaired(spark, sf_dir, name))) if rank is None else cut(rank.select(graphs.trade_vertex("code").alias("id"), "value"))
    return _references[key]


def show_rank(r: DataFrame) -> DataFrame:
    return r.select(F.col("id").alias("vertex"), F.round("value", 9).alias("score"))


def show_top(r: DataFrame) -> DataFrame:
    return r.select("position", F.col("id").alias("vertex"), F.round("value", 9).alias("score"))


def show_tally(t: DataFrame) -> DataFrame:
    return t.select(F.col("id").alias("vertex"), F.col("c").alias("walkers"))


# --- the method and its variants ---

def params(**more) -> walk.WalkParams:
    return walk.WalkParams(**({"n_walkers": N, "horizon": T, "rng": RNG, "counters": False} | more))


def tally_case(name: str, g: str, kind: str = "random", shards: int = 8, n: int = N, t: int = T, **more) -> None:
    sql = {"p_s": more.get("refresh_rate", 1.0), "rounding": more.get("rounding", "ceil"), "weight": more.get("replica_weight", "equal"), "force": more.get("erasure", "at_least_one") == "at_least_one"}
    case(name, f"WITH {o.tally(g, n, t, kind=kind, shards=shards, **sql)} SELECT id AS vertex, c AS walkers FROM tally")(
        lambda spark, d: show_tally(walk.walker_tally(placed(spark, d, g, kind, shards), params(n_walkers=n, horizon=t, **more)).tally)
    )


tally_case("walker_tally_trade", "trade", refresh_rate=0.7)
tally_case("walker_tally_words", "words", refresh_rate=0.7)
tally_case("walker_tally_full_refresh", "trade")
tally_case("walker_tally_exact_split", "trade", refresh_rate=0.4, rounding="exact")
tally_case("walker_tally_degree_split", "trade", refresh_rate=0.4, replica_weight="degree", rounding="exact")
tally_case("walker_tally_independent", "similarity", refresh_rate=0.4, erasure="independent", n=1000)
tally_case("walker_tally_by_source", "customers", kind="source", refresh_rate=0.4)
tally_case("walker_tally_grid", "activity", kind="grid", refresh_rate=0.4)
tally_case("walker_tally_chunked", "trade", kind="chunked", refresh_rate=0.4)
tally_case("walker_tally_toy", "toy", n=1000, shards=2, refresh_rate=0.5)


@case("walker_birth", f"WITH {o.graph('trade')}, {o.index()}, {o.births(N)} SELECT walker, id AS vertex FROM born")
def _(spark, d):
    verts = prepare.vertices(repaired(spark, d, "trade"))
    return walk.birth_uniform(verts, N, RNG).select("walker", F.col("id").alias("vertex"))


@case("walker_birth_seeded", f"WITH {o.tally('trade', N, 2, seeded=chr(115) + 'tarts_with(id, ' + chr(39) + 'c1' + chr(39) + ')')} SELECT id AS vertex, c AS walkers FROM tally")
def _(spark, d):
    lay = placed(spark, d, "trade")
    born = walk.birth_seeded(lay.vertices.where("startswith(id, 'c1')"), N, RNG).groupBy("id").agg(F.count("*").alias("k"))
    return show_tally(walk.walker_tally(lay, params(horizon=2), born).tally)


@case("walker_birth_per_vertex", f"WITH {o.graph('trade')} SELECT id AS vertex, kb AS k FROM ({o.binomial(f"SELECT id, {N}::DOUBLE AS k, 1.0::DOUBLE / (SELECT count(*) FROM v) AS p, {o.RNG.sql('b', 1, 'id')} AS key FROM v", 'id')}) WHERE kb > 0")
def _(spark, d):
    lay = placed(spark, d, "trade")
    return walk.birth_per_vertex(lay.vertices, N, RNG, lay.n).select(F.col("id").alias("vertex"), "k")


@case("walker_lives", f"WITH {o.graph('trade')}, {o.index()}, {o.births(N)} SELECT walker, id AS vertex, ({' + '.join(f'(u < {int(0.85 ** s * (1 << 60))})::INT' for s in range(1, T + 1))})::INT AS life FROM (SELECT walker, id, {o.RNG.sql('l', 0, 'walker')} AS u FROM born)")
def _(spark, d):
    born = walk.birth_uniform(prepare.vertices(repaired(spark, d, "trade")), N, RNG)
    return born.join(walk.lives(spark, N, 0.15, T, RNG), "walker").select("walker", F.col("id").alias("vertex"), "life")


FIRST = f"{o.graph('trade')}, {o.replicas()}, {o.index()}, {o.births(N)}, w0 AS MATERIALIZED (SELECT id, count(*) AS k FROM born GROUP BY id), {o.thinned(0)}"


def _first(spark, d):
    lay = placed(spark, d, "trade")
    born = walk.birth_uniform(lay.vertices, N, RNG, lay.n).groupBy("id").agg(F.count("*").alias("k"))
    t = walk.thin(born, 0.15, 0, RNG)
    return lay, t, t.where("k > stopped").select(F.col("id").alias("src"), (F.col("k") - F.col("stopped")).alias("k"))


@case("walker_death", f"WITH {FIRST} SELECT id AS vertex, k, stopped::BIGINT AS stopped FROM th0")
def _(spark, d):
    return _first(spark, d)[1].select(F.col("id").alias("vertex"), "k", "stopped")


@case("walker_cutoff", f"WITH {o.tally('trade', N, 1)} SELECT id AS vertex, k AS walkers FROM w1")
def _(spark, d):
    lay, _, alive = _first(spark, d)
    shares = walk.split_shares(alive, lay.directory, 0, RNG)
    return walk.pick_in_replica(shares, lay.replicas, 0, RNG).select(F.col("id").alias("vertex"), F.col("k").alias("walkers"))


for _name, _force in (("replica_refresh", False), ("refresh_force_one", True)):
    @case(_name, f"WITH {FIRST}, {o.live(0, 'al0', 0.4, _force)} SELECT src AS vertex, shard, d_local FROM lv0")
    def _(spark, d, force=_force):
        lay, _, alive = _first(spark, d)
        live = erasure.live_replicas(lay.directory.join(alive, "src"), 0.4, 0, RNG, force)
        return live.select(F.col("src").alias("vertex"), F.explode("reps").alias("r")).select("vertex", "r.shard", F.col("r.d_local").cast("long").alias("d_local"))

for _name, _round, _weight in (("scatter_split_ceil", "ceil", "equal"), ("scatter_split_exact", "exact", "equal"), ("scatter_split_degree", "exact", "degree")):
    @case(_name, f"WITH {FIRST}, {o.live(0, 'al0', 0.7)}, {o.shares(0, _round, _weight)} SELECT src AS vertex, shard, k FROM sh0")
    def _(spark, d, rounding=_round, weight=_weight):
        lay, _, alive = _first(spark, d)
        live = erasure.live_replicas(alive.join(lay.directory, "src"), 0.7, 0, RNG)
        return walk.split_shares(None, live, 0, RNG, rounding, weight).select(F.col("src").alias("vertex"), "shard", "k")


@case("scatter_pick", f"WITH {FIRST}, {o.live(0, 'al0', 0.7)}, {o.shares(0)}, {o.picks(0)} SELECT id AS vertex, k FROM w1")
def _(spark, d):
    lay, _, alive = _first(spark, d)
    live = erasure.live_replicas(alive.join(lay.directory, "src"), 0.7, 0, RNG)
    return walk.pick_in_replica(walk.split_shares(None, live, 0, RNG), lay.replicas, 0, RNG).select(F.col("id").alias("vertex"), "k")


for _name, _unbiased in (("scatter_binomial", False), ("scatter_binomial_unbiased", True)):
    _p = "1 / (d_out * 0.7::DOUBLE + pow(0.3::DOUBLE, d_out))" if _unbiased else "least(1, 1 / (d_out * 0.7::DOUBLE))"
    _edges = f"SELECT l.src, l.k::DOUBLE AS k, r.dst AS id, {_p} AS p, {o.RNG.sql('n', 0, 'l.src', 'r.dst')} AS key FROM lv0 l JOIN (SELECT src, shard, unnest(nbrs) AS dst FROM rep) r ON l.src = r.src AND l.shard = r.shard JOIN (SELECT src, count(*) AS d_out FROM edges GROUP BY src) d ON d.src = l.src"

    @case(_name, f"WITH {FIRST}, {o.live(0, 'al0', 0.7)} SELECT id AS vertex, sum(kb)::BIGINT AS k FROM ({o.binomial(_edges, 'src, id')}) WHERE kb > 0 GROUP BY id")
    def _(spark, d, unbiased=_unbiased):
        lay, _, alive = _first(spark, d)
        live = erasure.live_replicas(alive.join(lay.directory, "src"), 0.7, 0, RNG)
        return walk.scatter_binomial(live, lay.replicas, 0.7, 0, RNG, unbiased).select(F.col("id").alias("vertex"), "k")

for _name, _how in (("scatter_live_uniform", "live"), ("blocking_walk", "blocking"), ("serial_walk", "serial")):
    @case(_name, f"WITH {o.identity('trade', 500, 3, 0.4, _how)} SELECT walker, id AS vertex, step, stopped, blocked FROM pos")
    def _(spark, d, how=_how):
        return walk.identity_walk(repaired(spark, d, "trade"), 500, 3, 0.15, 0.4, RNG, how).select("walker", F.col("id").alias("vertex"), "step", "stopped", "blocked")


@case("walker_lives_walk", f"WITH {o.identity('trade', 500, 3, 0.4, 'live', at_birth=True)} SELECT walker, id AS vertex, step, stopped, blocked FROM pos")
def _(spark, d):
    return walk.identity_walk(repaired(spark, d, "trade"), 500, 3, 0.15, 0.4, RNG, death="at_birth").select("walker", F.col("id").alias("vertex"), "step", "stopped", "blocked")


@case("independent_walk", f"WITH {o.identity('trade', 500, 3, 1.0)} SELECT walker, id AS vertex, step, stopped, blocked FROM pos")
def _(spark, d):
    return walk.identity_walk(repaired(spark, d, "trade"), 500, 3, 0.15, 1.0, RNG).select("walker", F.col("id").alias("vertex"), "step", "stopped", "blocked")


def _teleport_sql() -> str:
    parts = [o.graph("trade"), o.index(), o.births(N), "ls AS MATERIALIZED (SELECT src, list(dst ORDER BY dst) AS nbrs, count(*) AS d FROM edges GROUP BY src)", "p0 AS (SELECT walker, id FROM born)"]
    for s in range(3):
        jump = f"{o.RNG.sql('d', s, 'walker')} < {o.threshold(0.15)}"
        parts.append(f"p{s + 1} AS MATERIALIZED (SELECT walker, nbrs[1 + {o.RNG.sql('p', s, 'walker')} % d] AS id FROM p{s} JOIN ls ON id = src WHERE NOT {jump} UNION ALL SELECT walker, idx.id FROM p{s} JOIN idx ON ix = {o.RNG.sql('t', s, 'walker')} % (SELECT count(*) FROM v) WHERE {jump})")
    return f"WITH {', '.join(parts)} SELECT id AS vertex, count(*) AS walkers FROM p3 GROUP BY id"


@case("teleport_walk", _teleport_sql())
def _(spark, d):
    return show_tally(walk.teleport_walk(repaired(spark, d, "trade"), N, 3, 0.15, RNG))


@case("walker_no_horizon", f"WITH {o.tally('activity', N, 60)} SELECT id AS vertex, c AS walkers FROM tally")
def _(spark, d):
    return show_tally(walk.walker_tally(placed(spark, d, "activity"), params(horizon=None, max_steps=60, counters=False)).tally)


@case("combine_walkers", f"WITH {FIRST} SELECT substr(id, 1, 2) AS vertex, sum(k)::BIGINT AS k FROM w0 GROUP BY 1")
def _(spark, d):
    lay = placed(spark, d, "trade")
    born = walk.birth_uniform(lay.vertices, N, RNG, lay.n).select(F.substring("id", 1, 2).alias("id"), F.lit(1).alias("k"))
    return walk.combine(born).select(F.col("id").alias("vertex"), "k")


for _name, _how, _sql in (("estimate", "n", f"c / {N}::DOUBLE"), ("estimate_total", "total", "c / (SELECT sum(c) FROM tally)::DOUBLE")):
    @case(_name, f"WITH {o.tally('trade', N, 2, p_s=0.4)} SELECT id AS vertex, round({_sql}, 9) AS score FROM tally")
    def _(spark, d, how=_how):
        return show_rank(walk.estimate(walk.walker_tally(placed(spark, d, "trade"), params(horizon=2, refresh_rate=0.4)).tally, N, how))


@case("step_counters", f"""WITH {o.tally('trade', N, 3, p_s=0.7)} {' UNION ALL '.join(f'''SELECT {s} AS step, (SELECT sum(k)::BIGINT FROM th{s}) AS alive_in, (SELECT sum(stopped)::BIGINT FROM th{s}) AS stopped, (SELECT count(*) FROM mt{s}) AS refresh_tried,
  (SELECT count(*) FROM lv{s}) AS refresh_sent, (SELECT count(*) FROM w{s + 1}) AS destinations, (SELECT sum(k)::BIGINT FROM w{s + 1}) AS alive_out''' for s in range(3))}""")
def _(spark, d):
    steps = walk.walker_tally(placed(spark, d, "trade"), params(horizon=3, refresh_rate=0.7, counters=True)).steps
    names = ["step", "alive_in", "stopped", "refresh_tried", "refresh_sent", "destinations", "alive_out"]
    return spark.createDataFrame([tuple(s[n] for n in names) for s in steps], "step int, " + ", ".join(f"{n} bigint" for n in names[1:]))


@case("traffic_model", f"""WITH {o.tally('trade', N, 3, p_s=0.4)}, b(step, sent, dest) AS ({' UNION ALL '.join(f'SELECT {s}, (SELECT count(*) FROM lv{s}), (SELECT count(*) FROM w{s + 1})' for s in range(3))})
  SELECT 'walker' AS method, (16 * sum(sent + dest))::BIGINT AS bytes FROM b UNION ALL SELECT 'baseline2', (2 * 2 * 16 * (count(*) - count(DISTINCT src)))::BIGINT FROM rep""")
def _(spark, d):
    lay = placed(spark, d, "trade")
    steps = walk.walker_tally(lay, params(horizon=3, refresh_rate=0.4, counters=True)).steps
    mine = spark.createDataFrame([("walker", cost.walker_model_bytes(steps))], "method string, bytes bigint")
    return mine.union(cost.baseline_model_bytes(lay, 2).select(F.lit("baseline2"), F.col("bytes").cast("long")))


@case("gossip_spread", f"""WITH {o.graph('customers')}, {o.replicas()}, k0 AS (SELECT id, 0 AS round FROM v WHERE id IN ('c1', 'c2', 'c4')), """ + ", ".join(
    f"al{r} AS (SELECT id AS src, 1 AS k FROM k{r}), {o.live(r, f'al{r}', 0.4)}, k{r + 1} AS MATERIALIZED (SELECT id, min(round)::INT AS round FROM (SELECT * FROM k{r} UNION ALL SELECT r.nbrs[1 + {o.RNG.sql('g', r, 'l.src', 'l.shard')} % r.d_local], {r + 1} FROM lv{r} l JOIN rep r ON l.src = r.src AND l.shard = r.shard) GROUP BY id)" for r in range(3)) + " SELECT id AS vertex, round FROM k3")
def _(spark, d):
    lay = placed(spark, d, "customers")
    return walk.gossip(lay.vertices.where("id in ('c1', 'c2', 'c4')"), lay, 3, 0.4, RNG).select(F.col("id").alias("vertex"), "round")


# --- erasures ---

@case("erasure_independent", f"WITH {o.graph('customers')} SELECT src, dst FROM edges WHERE {o.RNG.sql('e', 0, 'src', 'dst')} < {o.threshold(0.1)}")
def _(spark, d):
    return erasure.independent(repaired(spark, d, "customers"), 0.1, 0, RNG)


@case("erasure_at_least_one", f"""WITH {o.graph('items')}, x AS (SELECT src, dst, {o.RNG.sql('e', 0, 'src', 'dst')} < {o.threshold(0.1)} AS live, row_number() OVER (PARTITION BY src ORDER BY {o.RNG.sql('f', 0, 'src', 'dst')}, dst) AS r FROM edges)
  SELECT src, dst FROM x WHERE live UNION ALL SELECT src, dst FROM x WHERE r = 1 AND src NOT IN (SELECT src FROM x WHERE live)""")
def _(spark, d):
    return erasure.at_least_one(repaired(spark, d, "items"), 0.1, 0, RNG)


@case("erasure_by_replica", f"WITH {o.graph('customers')}, {o.replicas()}, al0 AS (SELECT DISTINCT src, 1 AS k FROM rep), {o.live(0, 'al0', 0.4)} SELECT r.src, unnest(nbrs) AS dst FROM lv0 JOIN rep r ON lv0.src = r.src AND lv0.shard = r.shard")
def _(spark, d):
    lay = placed(spark, d, "customers")
    return erasure.by_replica(lay.replicas, lay.directory, 0.4, 0, RNG)


@case("erasure_audit")
def _(spark, d):
    return erasure.audit(graphs.toy(spark), 0.5, 60, "at_least_one", RNG)


@case("live_probability", f"WITH {o.graph('trade')} SELECT d::INT AS d, p_s::DOUBLE AS p_s, round(p_s + pow(1 - p_s, d) / d, 9)::DOUBLE AS live, round((p_s + pow(1 - p_s, d) / d) / d + (1 - 1.0 / d) * p_s * p_s, 9)::DOUBLE AS no_block FROM (SELECT DISTINCT d::DOUBLE AS d FROM (SELECT count(*) AS d FROM edges GROUP BY src)) CROSS JOIN (SELECT unnest([0.1, 0.4, 0.5, 0.7, 1.0])::DOUBLE AS p_s)")
def _(spark, d):
    # the degrees that the graph has
    grid = baselines.with_degree(repaired(spark, d, "trade")).select(F.col("d").cast("int").alias("d")).distinct().withColumn("p_s", F.explode(F.array(*map(F.lit, (0.1, 0.4, 0.5, 0.7, 1.0)))))
    x = F.col("d").cast("double")
    return grid.select("d", "p_s", F.round(erasure.live_probability(x, F.col("p_s")), 9).alias("live"), F.round(erasure.no_block_probability(x, F.col("p_s")), 9).alias("no_block"))


# --- preparation ---

@case("graph_simple", f"WITH {o.graph('activity', 'none')} SELECT src, dst FROM edges")
def _(spark, d):
    return graphs.activity(spark, d)


for _g in ("words", "words_w3", "trade", "customers", "similarity", "links", "items", "turns", "sentences"):
    @case(f"graph_{_g}", f"SELECT count(*)::BIGINT AS edges, count(DISTINCT src)::BIGINT AS sources, count(DISTINCT dst)::BIGINT AS targets, sum(('0x' || substr(md5(src || '>' || dst), 1, 8))::BIGINT)::BIGINT AS checksum FROM ({o.GRAPHS[_g]})")
    def _(spark, d, g=_g):
        x = F.conv(F.substring(F.md5(F.concat_ws(">", "src", "dst").cast("binary")), 1, 8), 16, 10).cast("long")
        return graph(spark, d, g).agg(F.count("*").alias("edges"), F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("targets"), F.sum(x).alias("checksum"))


@case("degrees", f"WITH {o.graph('trade')} SELECT v.id AS vertex, coalesce(i, 0)::BIGINT AS d_in, coalesce(u, 0)::BIGINT AS d_out FROM v LEFT JOIN (SELECT dst AS id, count(*) AS i FROM edges GROUP BY dst) USING (id) LEFT JOIN (SELECT src AS id, count(*) AS u FROM edges GROUP BY src) USING (id)")
def _(spark, d):
    return prepare.degrees(repaired(spark, d, "trade")).select(F.col("id").alias("vertex"), "d_in", "d_out")


@case("dangling_list", f"WITH {o.graph('links', 'none')} SELECT DISTINCT dst AS vertex FROM edges WHERE dst NOT IN (SELECT src FROM edges)")
def _(spark, d):
    return prepare.dangling(graphs.links(spark, d)).select(F.col("id").alias("vertex"))


for _p in ("self_loop", "reverse_edge"):
    @case(f"dangling_{_p}", f"WITH {o.graph('links', _p)} SELECT src, dst FROM edges")
    def _(spark, d, p=_p):
        return prepare.repair(cut(graphs.links(spark, d)), p)


@case("dangling_drop", f"WITH {o.graph('items', 'none')}, " + ", ".join(f"e{i + 1} AS MATERIALIZED (SELECT * FROM {'edges' if i == 0 else f'e{i}'} WHERE dst IN (SELECT src FROM {'edges' if i == 0 else f'e{i}'}))" for i in range(40)) + " SELECT src, dst FROM e40")
def _(spark, d):
    return prepare.repair(cut(graphs.items(spark, d)), "drop")


@case("encode_ids", f"WITH {o.graph('trade')} SELECT count(*)::BIGINT AS vertices, count(DISTINCT id)::BIGINT AS ids, (SELECT count(*) FROM edges)::BIGINT AS edges FROM v")
def _(spark, d):
    edges, keys = prepare.encode(repaired(spark, d, "trade"))
    return keys.agg(F.count("*").alias("vertices"), F.countDistinct("id").alias("ids")).crossJoin(edges.agg(F.count("*").alias("edges")))


@case("graph_summary", f"WITH {o.graph('trade')} SELECT (SELECT count(*) FROM v)::BIGINT AS n, (SELECT count(*) FROM edges)::BIGINT AS m, (SELECT max(c) FROM (SELECT count(*) AS c FROM edges GROUP BY src))::BIGINT AS most_out, (SELECT max(c) FROM (SELECT count(*) AS c FROM edges GROUP BY dst))::BIGINT AS most_in")
def _(spark, d):
    return prepare.degrees(repaired(spark, d, "trade")).agg(F.count("*").alias("n"), F.sum("d_out").alias("m"), F.max("d_out").alias("most_out"), F.max("d_in").alias("most_in"))


@case("tail_exponent", f"WITH {o.graph('words')}, d AS (SELECT count(*) AS d FROM edges GROUP BY dst), h AS (SELECT d, count(*) AS c FROM d GROUP BY d) SELECT round(1 - regr_slope(ln(above), ln(d)), 6) AS theta FROM (SELECT d, sum(c) OVER (ORDER BY d DESC) AS above FROM h)")
def _(spark, d):
    from pyspark.sql import Window as W
    h = prepare.degrees(repaired(spark, d, "words")).where("d_in > 0").groupBy("d_in").agg(F.count("*").alias("c"))
    above = h.withColumn("above", F.sum("c").over(W.orderBy(F.desc("d_in"))))  # a row a degree
    return above.agg(F.round(1 - F.regr_slope(F.ln("above"), F.ln("d_in")), 6).alias("theta"))


for _k in ("random", "grid", "source", "chunked"):
    @case(f"layout_{_k}", f"WITH {o.graph('trade')}, {o.replicas(_k)} SELECT src AS vertex, shard::BIGINT AS shard, d_local::BIGINT AS d_local, md5(array_to_string(nbrs, ',')) AS nbrs FROM rep")
    def _(spark, d, k=_k):
        return placed(spark, d, "trade", k).replicas.select(F.col("src").alias("vertex"), F.col("shard").cast("long").alias("shard"), F.col("d_local").cast("long").alias("d_local"), F.md5(F.array_join("nbrs", ",").cast("binary")).alias("nbrs"))


@case("replication_factor", f"WITH {o.graph('trade')}, {o.replicas()} SELECT round(count(*) / count(DISTINCT src)::DOUBLE, 9) AS replication_factor FROM rep")
def _(spark, d):
    return placed(spark, d, "trade").replication().select(F.round("replication_factor", 9).alias("replication_factor"))


# --- baselines ---

for _i in (1, 2, 4):
    @case(f"rank_iter{_i}", f"WITH {o.graph('trade')}, {o.ranks(_i)} SELECT id AS vertex, round(value, 9) AS score FROM r{_i}")
    def _(spark, d, i=_i):
        return show_rank(baselines.fixed(repaired(spark, d, "trade"), i))


@case("rank_exact_small", f"WITH {o.graph('toy')}, {o.ranks(60)} SELECT id AS vertex, round(value, 9) AS score FROM r60")
def _(spark, d):
    return show_rank(baselines.fixed(graphs.toy(spark), 60))


for _g in ("trade", "words"):
    @case(f"rank_exact_{_g}", f"WITH RECURSIVE {o.graph(_g)}, {o.exact(degrees=True)} SELECT id AS vertex, round(value, 9) AS score FROM rx")
    def _(spark, d, g=_g):
        return show_rank(reference(spark, d, g))


@case("rank_runner2", f"WITH {o.graph('trade')}, {o.ranks(2)} SELECT id AS vertex, round(value, 9) AS score FROM r2")
def _(spark, d):
    lay = placed(spark, d, "trade")
    return show_rank(walk.run(walk.power_program(lay), lay, 2))


@case("walker_runner", f"WITH {o.tally('trade', N, T, p_s=0.7)} SELECT id AS vertex, c AS walkers FROM tally")
def _(spark, d):
    lay = placed(spark, d, "trade")
    return show_tally(walk.run(walk.walker_program(params(refresh_rate=0.7)), lay, T))


@case("walker_tally_bucketed", f"WITH {o.tally('trade', N, T, p_s=0.7)} SELECT id AS vertex, c AS walkers FROM tally")
def _(spark, d):
    # tables that outlive the query belong to sessions of their own: the joins are those of bucketed replicas, the frames are not tables here
    lay = placed(spark, d, "trade")
    by_source = replace(lay, bucketed=True)
    born = walk.birth_uniform(lay.vertices, N, RNG, lay.n, lay.index).groupBy("id").agg(F.count("*").alias("k"))
    return show_tally(walk.walker_tally(by_source, params(refresh_rate=0.7, broadcast=0), born).tally)


@case("rank_to_all", f"WITH {o.graph('links', 'none')}, {o.ranks(2, to_all=True)} SELECT id AS vertex, round(value, 9) AS score FROM r2")
def _(spark, d):
    return show_rank(baselines.fixed(cut(graphs.links(spark, d)), 2, to_all=True))


STOPS = """{ed}, it(i, id, value, moved) AS (SELECT 0, id, 1.0::DOUBLE / (SELECT count(*) FROM v)::DOUBLE, 1e9::DOUBLE FROM v UNION ALL SELECT i + 1, id, new, sum(abs(new - value)) OVER () FROM (
  SELECT o.i, o.id, o.value, coalesce(m, 0) * 0.85::DOUBLE + 0.15::DOUBLE / (SELECT count(*) FROM v) AS new FROM it o LEFT JOIN (SELECT dst AS id, sum(value / d) AS m FROM ed JOIN it ON src = id GROUP BY dst) q USING (id) WHERE o.moved >= 1e-3))"""
ED = "ed AS MATERIALIZED (SELECT e.src, e.dst, d.d FROM edges e JOIN (SELECT src, count(*) AS d FROM edges GROUP BY src) d USING (src))"


@case("rank_tolerance", f"WITH RECURSIVE {o.graph('activity')}, {STOPS.format(ed=ED)} SELECT id AS vertex, round(value, 9) AS score, i::INT AS iterations FROM it WHERE i = (SELECT max(i) FROM it)")
def _(spark, d):
    rank, n = baselines.tolerance(repaired(spark, d, "activity"), 1e-3)
    return show_rank(rank).withColumn("iterations", F.lit(n))


@case("rank_delta", f"""WITH RECURSIVE {o.graph('activity')}, {ED}, it(i, id, value, change, most) AS (SELECT 0, id, 0.15::DOUBLE / (SELECT count(*) FROM v), 0.15::DOUBLE / (SELECT count(*) FROM v), 1e9::DOUBLE FROM v UNION ALL
  SELECT i + 1, id, value + m, change2, max(abs(change2)) OVER () FROM (SELECT o.i, o.id, o.value, coalesce(q.m, 0) AS m, CASE WHEN abs(o.change) > 1e-5 THEN 0 ELSE o.change END + coalesce(q.m, 0) AS change2
  FROM it o LEFT JOIN (SELECT dst AS id, sum(change / d * 0.85::DOUBLE) AS m FROM ed JOIN it ON src = id WHERE abs(change) > 1e-5 GROUP BY dst) q USING (id) WHERE o.most > 1e-5)) SELECT id AS vertex, round(value, 9) AS score FROM it WHERE i = (SELECT max(i) FROM it)""")
def _(spark, d):
    return show_rank(baselines.delta(repaired(spark, d, "activity"), 1e-5)[0])


KEPT = f"kept AS MATERIALIZED (SELECT src, dst FROM edges WHERE {o.RNG.sql('s', 0, 'src', 'dst')} >= {o.threshold(0.5)}), kr AS MATERIALIZED (SELECT * FROM kept UNION ALL SELECT id, id FROM v WHERE id NOT IN (SELECT src FROM kept))"


@case("sparsify_r50", f"WITH {o.graph('trade')}, {KEPT} SELECT src, dst FROM kept")
def _(spark, d):
    return baselines.sparsified(repaired(spark, d, "trade"), 0.5, RNG)


for _name, _deg in (("sparsify_rank", None), ("sparsify_reweighted", "edges")):
    @case(_name, f"WITH {o.graph('trade')}, {KEPT}, {o.ranks(2, edges='kr', degrees=_deg)} SELECT id AS vertex, round(value, 9) AS score FROM r2")
    def _(spark, d, re=_deg is not None):
        return show_rank(baselines.sparsified_rank(repaired(spark, d, "trade"), 0.5, 2, rng=RNG, reweight=re))


@case("rank_indegree", f"WITH {o.graph('trade')} SELECT v.id AS vertex, round(coalesce(c, 0) / (SELECT count(*) FROM edges)::DOUBLE, 9) AS score FROM v LEFT JOIN (SELECT dst AS id, count(*) AS c FROM edges GROUP BY dst) USING (id)")
def _(spark, d):
    return show_rank(baselines.in_degree(repaired(spark, d, "trade")))


@case("series_equals_power", f"WITH {o.graph('trade')}, {o.ranks(3)} SELECT id AS vertex, round(value, 9) AS score FROM r3")
def _(spark, d):
    return show_rank(baselines.series(repaired(spark, d, "trade"), 3))


# (the similarity graph's degrees are 8: two iterations give scores that lie half-way between rounded ones)
for _g, _i in (("trade", 2), ("similarity", 5), ("words", 2)):
    @case(f"topk_{_g}", f"WITH {o.graph(_g)}, {o.ranks(_i)} {o.top(f'r{_i}', 50)}")
    def _(spark, d, g=_g, i=_i):
        return show_top(walk.top_k(baselines.fixed(repaired(spark, d, g), i), 50))


# --- accuracy: the tally's estimate or one iteration against the converged vector ---

NEAR = f"WITH RECURSIVE {o.graph('similarity')}, {o.ranks(1)}, {o.exact()}"
REF = f"{NEAR}, a AS (SELECT * FROM r1 ORDER BY round(value, 12) DESC, id LIMIT 20), b AS (SELECT * FROM rx ORDER BY round(value, 12) DESC, id LIMIT 20)"


def _pair(spark, d):
    e = repaired(spark, d, "similarity")
    return cut(baselines.fixed(e, 1)), reference(spark, d, "similarity")


@case("mass_captured", f"{REF} SELECT 20 AS k, round(sum(rx.value), 9) AS mass FROM a JOIN rx USING (id)")
def _(spark, d):
    a, b = _pair(spark, d)
    return accuracy.mass_captured(a, b, 20).select("k", F.round("mass", 9).alias("mass"))


@case("mass_captured_norm", f"{REF} SELECT 20 AS k, round(sum(rx.value) / (SELECT sum(value) FROM b), 9) AS mass FROM a JOIN rx USING (id)")
def _(spark, d):
    a, b = _pair(spark, d)
    return accuracy.mass_captured(a, b, 20, normalised=True).select("k", F.round("mass", 9).alias("mass"))


@case("exact_identification", f"{REF} SELECT 20 AS k, count(*) AS hits, round(count(*) / 20.0::DOUBLE, 9) AS hit_share FROM a SEMI JOIN b USING (id)")
def _(spark, d):
    a, b = _pair(spark, d)
    return accuracy.identified(a, b, 20).select("k", "hits", F.round("hit_share", 9).alias("hit_share"))


def curve_sql(est: str, ref: str, ks: list[int]) -> str:
    return f"""SELECT k::INT AS k, round(mass, 9) AS mass, round(mass / best, 9) AS mass_norm, hits, round(hits / k::DOUBLE, 9) AS hit_share FROM (SELECT k, (SELECT sum(r.value) FROM x JOIN {ref} r USING (id) WHERE p <= k) AS mass,
      (SELECT sum(value) FROM y WHERE q <= k) AS best, (SELECT count(*) FROM x JOIN y USING (id) WHERE p <= k AND q <= k) AS hits FROM (SELECT unnest({ks}) AS k), (SELECT 1)
      ) , (SELECT 1) WHERE true""".replace("FROM x", "FROM (SELECT id, row_number() OVER (ORDER BY round(value, 12) DESC, id) AS p FROM " + est + ") x").replace("FROM y", "FROM (SELECT id, value, row_number() OVER (ORDER BY round(value, 12) DESC, id) AS q FROM " + ref + ") y").replace("JOIN y", "JOIN (SELECT id, row_number() OVER (ORDER BY round(value, 12) DESC, id) AS q FROM " + ref + ") y")


def show_curve(c: DataFrame) -> DataFrame:
    return c.select("k", F.round("mass", 9).alias("mass"), F.round("mass_norm", 9).alias("mass_norm"), "hits", F.round("hit_share", 9).alias("hit_share"))


@case("accuracy_curve", f"{NEAR} {curve_sql('r1', 'rx', [5, 10, 20, 50])}")
def _(spark, d):
    return show_curve(accuracy.curve(*_pair(spark, d), [5, 10, 20, 50]))


@case("rank_distance", f"{NEAR} SELECT round(sum(abs(a.value - b.value)), 9) AS l1, round(sqrt(sum((a.value - b.value) ** 2)), 9) AS l2, round(max(abs(a.value - b.value)), 9) AS linf, round(sum((a.value - b.value) ** 2 / b.value), 9) AS chi2 FROM r1 a JOIN rx b USING (id)")
def _(spark, d):
    return accuracy.distance(*_pair(spark, d)).select(*(F.round(c, 9).alias(c) for c in ("l1", "l2", "linf", "chi2")))


@case("chi2_contrast", f"WITH {o.graph('customers')}, {o.ranks(4)} SELECT round(sum((a.value - b.value) ** 2 / b.value), 9) AS chi2 FROM r2 a JOIN r4 b USING (id)")
def _(spark, d):
    e = repaired(spark, d, "customers")
    return accuracy.distance(baselines.fixed(e, 2), baselines.fixed(e, 4)).select(F.round("chi2", 9).alias("chi2"))


@case("loss_chain", f"""{REF}, z AS (SELECT (SELECT sum(value) FROM b) - (SELECT sum(rx.value) FROM a JOIN rx USING (id)) AS loss, sum(abs(a.value - b.value)) AS l1, sqrt(sum((a.value - b.value) ** 2 / b.value)) AS root_chi2 FROM r1 a JOIN rx b USING (id))
  SELECT round(loss, 9) AS loss, round(l1, 9) AS l1, round(root_chi2, 9) AS root_chi2, loss <= l1 + 1e-12 AND l1 <= root_chi2 + 1e-12 AS ok FROM z""")
def _(spark, d):
    return accuracy.loss_chain(*_pair(spark, d), 20).select(F.round("loss", 9).alias("loss"), F.round("l1", 9).alias("l1"), F.round("root_chi2", 9).alias("root_chi2"), "ok")


@case("rank_corr", f"""{REF}, p AS (SELECT b.id, b.value, row_number() OVER (ORDER BY round(b.value, 12) DESC, id) AS position, r1.value AS a FROM b JOIN r1 USING (id)), s AS (SELECT *, row_number() OVER (ORDER BY round(a, 12) DESC, id) AS p FROM p)
  SELECT 20 AS k, round(corr(p, position), 6) AS spearman, round((SELECT sum(rx.value / log2(p + 1)) FROM (SELECT id, row_number() OVER (ORDER BY round(value, 12) DESC, id) AS p FROM a) x JOIN rx USING (id)) / sum(value / log2(position + 1)), 6) AS ndcg FROM s""")
def _(spark, d):
    return accuracy.rank_corr(*_pair(spark, d), 20).select("k", F.round("spearman", 6).alias("spearman"), F.round("ndcg", 6).alias("ndcg"))


# --- theory ---

BOUNDS = ["mixing", "sampling", "total", "meeting", "chi2_decay", "interference", "second_moment", "meeting_power_law", "rank_tail", "chi2_start", "distance_tail"]


@case("bound_sweep", f"WITH {o.graph('trade')}, {o.ranks(2)}, " + """gr AS (SELECT 0.15::DOUBLE AS p_t, 0.1::DOUBLE AS delta, n, pi_max, t::INT AS t, k::INT AS k, n_walkers::INT AS n_walkers, p_s::DOUBLE AS p_s, 1 / n::DOUBLE + t / (0.15::DOUBLE * sqrt(n)) AS p_meet
  FROM (SELECT count(*) AS n, max(value) AS pi_max FROM r2), (SELECT unnest([3, 4, 10, 11, 40]) AS t), (SELECT unnest([10, 100]) AS k), (SELECT unnest([8000, 800000]) AS n_walkers), (SELECT unnest([1.0, 0.7, 0.4, 0.1])::DOUBLE AS p_s)), b AS (SELECT *, sqrt(pow(1 - p_t, t + 1) / p_t) AS mixing, sqrt(k / delta * (1 / n_walkers::DOUBLE + (1 - p_s * p_s) * p_meet)) AS sampling FROM gr)
  SELECT p_t, t, k, delta, n_walkers, p_s, round(mixing, 6) AS mixing, round(sampling, 6) AS sampling, round(mixing + sampling, 6) AS total, round(1 / n::DOUBLE + t * pi_max / p_t, 6) AS meeting, round((1 - p_t) / p_t * pow(1 - p_t, t), 6) AS chi2_decay,
  round((1 - p_s * p_s) * p_meet, 6) AS interference, round(1 / n_walkers::DOUBLE + (n_walkers - 1) * ((1 - p_s * p_s) * p_meet) / n_walkers, 6) AS second_moment, round(1 / n::DOUBLE + t / (p_t * sqrt(n)), 6) AS meeting_power_law,
  round(least(1, pow(n, 0.5::DOUBLE - 1 / 1.2::DOUBLE)), 6) AS rank_tail, round((1 - p_t) / p_t, 6) AS chi2_start, round(least(1, (1 / n_walkers::DOUBLE + (n_walkers - 1) * ((1 - p_s * p_s) * p_meet) / n_walkers) / (0.11::DOUBLE * 0.11::DOUBLE)), 6) AS distance_tail,
  greatest(1, ceil(ln(1 / 0.07::DOUBLE)))::INT AS plan_t, ceil(k / (0.07::DOUBLE * 0.07::DOUBLE))::BIGINT AS plan_n, ceil(3 * ln(2 / delta) / (0.11::DOUBLE * 0.11::DOUBLE * pi_max))::BIGINT AS chernoff FROM b""")
def _(spark, d):
    measured = baselines.fixed(repaired(spark, d, "trade"), 2).agg(F.count("*").alias("n"), F.max("value").alias("pi_max"))
    return theory.sweep(measured).select("p_t", "t", "k", "delta", "n_walkers", "p_s", *(F.round(c, 6).alias(c) for c in BOUNDS), "plan_t", "plan_n", "chernoff")


@case("meeting_mass", f"WITH {o.graph('similarity')}, {o.ranks(4)}, s AS ({' UNION ALL '.join(f'SELECT {i} AS step, sum(value * value) AS l2sq FROM r{i}' for i in range(5))}) SELECT step::INT AS step, round(l2sq, 9) AS l2sq, round(sum(l2sq) OVER (ORDER BY step), 9) AS cumulative FROM s")
def _(spark, d):
    return theory.meeting_mass(repaired(spark, d, "similarity"), 4).select("step", F.round("l2sq", 9).alias("l2sq"), F.round("cumulative", 9).alias("cumulative"))


@case("contraction", f"WITH {o.graph('similarity')}, {o.ranks(4)}, s AS ({' UNION ALL '.join(f'SELECT {i} AS step, sum(abs(a.value - b.value)) AS x FROM r{i} a JOIN r{i - 1} b USING (id)' for i in range(1, 5))}) SELECT step::INT AS step, round(x, 9) AS l1_delta, round(x / lag(x) OVER (ORDER BY step), 6) AS ratio FROM s")
def _(spark, d):
    return theory.contraction(repaired(spark, d, "similarity"), 4).select("step", F.round("l1_delta", 9).alias("l1_delta"), F.round("ratio", 6).alias("ratio"))


POS = o.identity("similarity", 1000, 3, 0.4, "blocking")


def _pos(spark, d, t=3):
    return cut(walk.identity_walk(repaired(spark, d, "similarity"), 1000, t, 0.15, 0.4, RNG, "blocking"))


@case("walkers_met", f"WITH {POS}, c AS (SELECT step, id, count(*) AS c FROM pos GROUP BY ALL) SELECT step, sum(c * (c - 1) // 2)::BIGINT AS pairs, round(sum(c * (c - 1) // 2) / (1000 * 999 / 2)::DOUBLE, 9) AS rate FROM c GROUP BY step")
def _(spark, d):
    return theory.meet_rate(_pos(spark, d), 1000).select("step", "pairs", F.round("rate", 9).alias("rate"))


@case("first_interference", f"""WITH {o.identity('activity', 1000, 3, 0.4, 'blocking')}, j AS (SELECT a.walker AS w, a.step FROM pos a JOIN pos b ON a.walker % 2 = 0 AND b.walker = a.walker + 1 AND a.step = b.step AND a.id = b.id),
  h AS (SELECT DISTINCT walker - walker % 2 AS w, step - 1 AS step FROM pos WHERE blocked) SELECT step, count(*) AS pairs FROM (SELECT w, min(step) AS step FROM j JOIN h USING (w, step) GROUP BY w) GROUP BY step""")
def _(spark, d):
    return theory.first_interference(cut(walk.identity_walk(repaired(spark, d, "activity"), 1000, 3, 0.15, 0.4, RNG, "blocking")))


@case("step_lengths", f"WITH {POS} SELECT step, count(*) AS stopped, round(CASE WHEN step < 3 THEN pow(0.85::DOUBLE, step) * 0.15 ELSE pow(0.85::DOUBLE, 3) END * 1000, 6) AS expected FROM pos WHERE stopped GROUP BY step")
def _(spark, d):
    return theory.step_lengths(_pos(spark, d), 1000, 3).select("step", "stopped", F.round("expected", 6).alias("expected"))


@case("rank_floor", f"WITH RECURSIVE {o.graph('similarity')}, {o.ranks(3)}, {o.exact()} SELECT round(min(value), 9) AS least, round(max(value), 9) AS most, min(value) >= 0.15::DOUBLE / count(*) - 1e-15 AS floor_ok, (SELECT round(max(value), 9) FROM r3) AS walk_most, round(max(value) / 0.15::DOUBLE, 8) AS ceiling, (SELECT max(value) FROM r3) <= max(value) / 0.15::DOUBLE + 1e-15 AS ceiling_ok FROM rx")
def _(spark, d):
    e = repaired(spark, d, "similarity")
    got = theory.floor_ceiling(reference(spark, d, "similarity"), prepare.vertices(e).count(), walks=baselines.fixed(e, 3))
    return got.select(F.round("least", 9).alias("least"), F.round("most", 9).alias("most"), "floor_ok", F.round("walk_most", 9).alias("walk_most"), F.round("ceiling", 8).alias("ceiling"), "ceiling_ok")


@case("set_mass_gap", f"{NEAR}, d AS (SELECT abs(a.value - b.value) AS d FROM r1 a JOIN rx b USING (id)), z AS (SELECT (SELECT sum(d) FROM (SELECT d FROM d ORDER BY d DESC LIMIT 20)) AS gap, sqrt(sum(d * d)) * sqrt(20) AS bound FROM d) SELECT round(gap, 9) AS gap, round(bound, 9) AS bound, gap <= bound + 1e-12 AS ok FROM z")
def _(spark, d):
    return theory.set_mass_gap(*_pair(spark, d), 20).select(F.round("gap", 9).alias("gap"), F.round("bound", 9).alias("bound"), "ok")


@case("baseline_traffic_model", f"WITH {o.graph('trade')}, {o.replicas()} SELECT 2 AS iterations, (4 * (count(*) - count(DISTINCT src)))::BIGINT AS messages, (64 * (count(*) - count(DISTINCT src)))::BIGINT AS bytes FROM rep")
def _(spark, d):
    return cost.baseline_model_bytes(placed(spark, d, "trade"), 2).select("iterations", F.col("messages").cast("long").alias("messages"), F.col("bytes").cast("long").alias("bytes"))


# --- experiments at one fixed seed: accuracy of the tally against the converged vector ---

def experiment(name: str, g: str, axis: str, settings: list[tuple]) -> None:
    """settings: (value, n, t, p_s)."""
    one = lambda v, n, t, p: f"SELECT {v}::DOUBLE AS {axis}, * FROM (WITH RECURSIVE {o.tally(g, n, t, p_s=p)}, {o.exact(degrees=True)}, est AS (SELECT id, c / {n}::DOUBLE AS value FROM tally) {curve_sql('est', 'rx', [20])})"

    def query(spark, d):
        lay = placed(spark, d, g)
        ref = reference(spark, d, g)
        out = None
        for v, n, t, p in settings:
            est = walk.estimate(walk.walker_tally(lay, params(n_walkers=n, horizon=t, refresh_rate=p)).tally, n)
            row = show_curve(accuracy.curve(est, ref, [20])).select(F.lit(float(v)).alias(axis), "*")
            out = row if out is None else out.unionByName(row)
        return out

    case(name, " UNION ALL ".join(one(*s) for s in settings))(query)


experiment("experiment_sweep_n", "similarity", "n_walkers", [(n, n, 4, 1.0) for n in (500, 2000, 8000)])
experiment("experiment_sweep_t", "similarity", "t", [(t, 2000, t, 1.0) for t in (1, 2, 4)])
experiment("experiment_sweep_ps", "similarity", "p_s", [(p, 4000, 3, p) for p in (1.0, 0.7, 0.4, 0.1)])


@case("experiment_accuracy_k", f"WITH RECURSIVE {o.tally('trade', 4000, 4, p_s=0.7)}, {o.exact(degrees=True)}, est AS (SELECT id, c / 4000::DOUBLE AS value FROM tally) {curve_sql('est', 'rx', [10, 30, 100])}")
def _(spark, d):
    est = walk.estimate(walk.walker_tally(graphs.trade_layout(spark, d, RNG), params(n_walkers=4000, refresh_rate=0.7)).tally, 4000)
    return show_curve(accuracy.curve(est, reference(spark, d, "trade"), [10, 30, 100]))


@case("experiment_sparsify", f"WITH RECURSIVE {o.graph('similarity')}, {KEPT}, {o.ranks(2, edges='kr').replace('ed AS', 'sed AS').replace('FROM ed ', 'FROM sed ').replace('r0', 's0').replace('r1', 's1').replace('r2', 's2').replace('m0', 'n0').replace('m1', 'n1')}, {o.exact(degrees=True)} {curve_sql('s2', 'rx', [20])}")
def _(spark, d):
    e = repaired(spark, d, "similarity")
    return show_curve(accuracy.curve(baselines.sparsified_rank(e, 0.5, 2, rng=RNG), reference(spark, d, "similarity"), [20]))


# --- applications ---

def app(name: str, g: str, where: str, k: int, p_s: float = 0.7) -> None:
    """The k heaviest among the vertices that `where` admits, by walkers and by four iterations."""
    case(f"{name}_topk", f"WITH {o.tally(g, N, 3, p_s=p_s)}, est AS (SELECT id, c / {N}::DOUBLE AS value FROM tally WHERE {where}) {o.top('est', k)}")(
        lambda spark, d: show_top(walk.top_k(walk.estimate(walk.walker_tally(placed(spark, d, g), params(horizon=3, refresh_rate=p_s)).tally, N).where(where), k)))
    case(f"{name}_exact4", f"WITH {o.graph(g)}, {o.ranks(4)}, est AS (SELECT * FROM r4 WHERE {where}) {o.top('est', k)}")(
        lambda spark, d: show_top(walk.top_k(baselines.fixed(repaired(spark, d, g), 4).where(where), k)))


app("customers", "customers", "true", 20)
app("trade_customers", "trade", "id LIKE 'c%'", 20)
app("keywords", "words", "true", 20)
app("keywords_benchmark", "items", "true", 20)
app("keywords_user_turns", "turns", "true", 20)
app("sentences", "sentences", "true", 20)
app("users", "activity", "true", 20)
app("links", "links", "true", 20)


def _parts(spark, d, column: str) -> DataFrame:
    """Walkers for each value of a column of documents that the table has, null among them: the five heaviest words of each. One walk does for all values."""
    from pyspark.sql import Window as W
    rng, value = PartRng(), F.col(column).cast("string")
    part = F.coalesce(F.concat(F.lit("="), F.hex(value)), F.lit("-"))
    edges = cut(prepare.repair(cut(graphs.next_words(read(spark, d, "documents"), part=part))))
    reps, directory = prepare.replicated(edges, "random", 8, rng)
    verts = directory.select(F.col("src").alias("id"))
    born = walk.birth_in_parts(verts, N, rng).groupBy("id").agg(F.count("*").alias("k"))
    est = walk.estimate(walk.walker_tally(prepare.Layout(reps, directory, verts, 0, verts), params(horizon=3, refresh_rate=0.7, rng=rng), born).tally, N)
    of = F.substring_index("id", "|", 1)
    rows = est.withColumn("part", of).withColumn("position", F.row_number().over(W.partitionBy("part").orderBy(F.desc(F.round("value", 12)), "id"))).where("position <= 5")
    name = F.when(F.col("part") != "-", F.decode(F.unhex(F.substring("part", 2, 1 << 30)), "UTF-8")).alias(column)
    return rows.select(name, "position", F.substring_index("id", "|", -1).alias("vertex"), F.round("value", 9).alias("score"))


# (the SQL names the languages that the given tables have)
@case("keywords_by_lang", " UNION ALL ".join(f"SELECT '{x}' AS lang, * FROM (WITH {o.tally('words_' + x, N, 3, p_s=0.7)}, est AS (SELECT id, c / {N}::DOUBLE AS value FROM tally) {o.top('est', 5)})" for x in ("en", "de", "fr", "es")))
def _(spark, d):
    return _parts(spark, d, "lang")


@case("keywords_by_source")
def _(spark, d):
    return _parts(spark, d, "source")


for _k in (10, 100):
    @case(f"customers_named_top{_k}", f"""WITH {o.tally('customers', 4 * N, 3, p_s=0.7)}, est AS (SELECT id, c / {4 * N}::DOUBLE AS value FROM tally), t AS ({o.top('est', _k)})
      SELECT position, vertex, score, c_name AS name, n_name AS nation, c_mktsegment AS segment FROM t JOIN customer ON vertex = 'c' || c_custkey JOIN nation ON c_nationkey = n_nationkey""")
    def _(spark, d, k=_k):
        est = walk.estimate(walk.walker_tally(placed(spark, d, "customers"), params(n_walkers=4 * N, horizon=3, refresh_rate=0.7)).tally, 4 * N)
        top = F.broadcast(show_top(walk.top_k(est, k)))  # k rows
        who = read(spark, d, "customer").join(F.broadcast(read(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
        return who.join(top, F.col("vertex") == F.concat(F.lit("c"), F.col("c_custkey"))).select("position", "vertex", "score", F.col("c_name").alias("name"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"))


@case("sentences_by_document", f"""WITH {o.tally('sentences', 4 * N, 3, p_s=0.7)}, r AS (SELECT split_part(id, '_', 2)::BIGINT AS doc_id, split_part(id, '_', 3)::INT AS line, c, row_number() OVER (PARTITION BY split_part(id, '_', 2) ORDER BY c DESC, id) AS position FROM tally)
  SELECT doc_id, position::INT AS position, line, c AS walkers FROM r WHERE position <= 3""")
def _(spark, d):
    from pyspark.sql import Window as W
    tally = walk.walker_tally(placed(spark, d, "sentences"), params(n_walkers=4 * N, horizon=3, refresh_rate=0.7)).tally
    part = F.split("id", "_")
    rows = tally.withColumns({"doc_id": part[1].cast("long"), "line": part[2].cast("int")})
    return rows.withColumn("position", F.row_number().over(W.partitionBy("doc_id").orderBy(F.desc("c"), "id"))).where("position <= 3").select("doc_id", "position", "line", F.col("c").alias("walkers"))


# pages under each policy for vertices without out-edges
for _p in ("self_loop", "reverse_edge"):
    @case(f"links_{_p}_topk", f"WITH {o.graph('links', _p)}, {o.ranks(4)} {o.top('r4', 20)}")
    def _(spark, d, p=_p):
        return show_top(walk.top_k(baselines.fixed(cut(prepare.repair(cut(graphs.links(spark, d)), p)), 4), 20))


@case("links_to_all_topk", f"WITH {o.graph('links', 'none')}, {o.ranks(4, to_all=True)} {o.top('r4', 20)}")
def _(spark, d):
    return show_top(walk.top_k(baselines.fixed(cut(graphs.links(spark, d)), 4, to_all=True), 20))


@case("links_drop_topk", "SELECT 1::INT AS position, '' AS vertex, 0.0::DOUBLE AS score WHERE false")
def _(spark, d):
    # every target of the given pages dangles, so nothing is left
    return show_top(walk.top_k(baselines.fixed(prepare.repair(cut(graphs.links(spark, d)), "drop"), 4), 20))


@case("users_mixed_by_week_topk", f"""WITH {o.tally('mixed', 4 * N, 3, p_s=0.7)}, r AS (SELECT split_part(id, '|', 1) AS week, split_part(id, '|', 2) AS vertex, c, row_number() OVER (PARTITION BY split_part(id, '|', 1) ORDER BY c DESC, id) AS position FROM tally)
  SELECT week, position::INT AS position, vertex, c AS walkers FROM r WHERE position <= 10""")
def _(spark, d):
    # activity of each week beside who buys next: one graph of as many parts as weeks, so one walk ranks all windows
    from pyspark.sql import Window as W
    tally = walk.walker_tally(graphs.mixed_layout(spark, d, RNG), params(n_walkers=4 * N, horizon=3, refresh_rate=0.7)).tally
    part = F.split("id", "\\|")
    rows = tally.withColumns({"week": part[0], "vertex": part[1]})
    return rows.withColumn("position", F.row_number().over(W.partitionBy("week").orderBy(F.desc("c"), "id"))).where("position <= 10").select("week", "position", "vertex", F.col("c").alias("walkers"))


@case("users_mixed_topk", f"""WITH a AS ({o.GRAPHS['activity']}), c AS (SELECT 'u' || substr(src, 2) AS src, 'u' || substr(dst, 2) AS dst FROM ({o.GRAPHS['customers']})), w AS (SELECT src, dst, sum(w) AS w FROM (SELECT src, dst, 0.7::DOUBLE / (count(*) OVER (PARTITION BY src)) AS w FROM a UNION ALL
  SELECT src, dst, 0.3::DOUBLE / (count(*) OVER (PARTITION BY src)) FROM c) GROUP BY ALL), v AS (SELECT src AS id FROM w UNION SELECT dst FROM w), d AS (SELECT src, sum(w) AS d FROM w GROUP BY src), r1 AS (SELECT v.id, coalesce(m, 0) * 0.85::DOUBLE + 0.15::DOUBLE / (SELECT count(*) FROM v) AS value
  FROM v LEFT JOIN (SELECT dst AS id, sum(w / d) / (SELECT count(*) FROM v) AS m FROM w JOIN d USING (src) GROUP BY dst) USING (id)) {o.top('r1', 20)}""")
def _(spark, d):
    # activity and connectivity mixed as weights; equality of user and customer numbers is a synthetic link
    u = lambda c: F.concat(F.lit("u"), F.substring(c, 2, 20)).alias(c)
    from pyspark.sql import Window as W
    share = lambda e, a: e.withColumn("w", F.lit(a) / F.count("*").over(W.partitionBy("src")))
    both = share(graphs.activity(spark, d), 0.7).unionByName(share(graphs.customers(spark, d).select(u("src"), u("dst")), 0.3)).groupBy("src", "dst").agg(F.sum("w").alias("w"))
    both = cut(both)
    verts = cut(prepare.vertices(both))
    n = verts.count()
    sent = both.join(both.groupBy("src").agg(F.sum("w").alias("d")), "src").groupBy(F.col("dst").alias("id")).agg((F.sum(F.col("w") / F.col("d")) / n).alias("m"))
    rank = verts.join(sent, "id", "left").select("id", (F.coalesce("m", F.lit(0.0)) * 0.85 + 0.15 / n).alias("value"))
    return show_top(walk.top_k(rank, 20))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 heaviest vertices of the trade graph by walkers, with a part of the replicas refreshed."""
    lay = placed(spark, sf_dir, "trade")
    return show_top(walk.top_k(walk.estimate(walk.walker_tally(lay, params(refresh_rate=0.7)).tally, N), 20))


__all__ = ["O", "Q", "flagship", "read"]
