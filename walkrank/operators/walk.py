"""The walker-tally method: few discrete walkers move a few steps, stop at random, and are counted where they stop.

State is a table of counts (id, k): walkers have no identity, and those that meet merge. A step: each walker
stops with probability p_T (thin); a vertex refreshes a random share p_s of its replicas (one at least under
"at_least_one"); its walkers leave only through those (scatter); what arrives is merged (combine). After
`horizon` steps the rest are counted too. All draws are keyed hashes, so retried tasks repeat them.

The walker table has at most `n_walkers` rows whatever the graph's size (the rounding up of a split can add a few), so it
may be broadcast against the adjacency behind a check of that bound. Each step's walkers feed two consumers (those that
stop, those that go on); they are cached, so the adjacency is read once a step, and, every few steps, checkpointed with the
tally so far, after which the cache is freed.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng
from walkrank.functions.session import cut, small
from walkrank.operators.erasure import live_replicas
from walkrank.operators.prepare import Layout, indexed


#: Steps between checkpoints.
EVERY = 6


@dataclass(frozen=True)
class WalkParams:
    n_walkers: int = 800_000
    horizon: int | None = 4
    stop_rate: float = 0.15
    refresh_rate: float = 1.0
    erasure: str = "at_least_one"  # or "independent"
    scatter: str = "split"  # or "binomial", "binomial_unbiased"
    rounding: str = "ceil"  # or "exact"
    replica_weight: str = "equal"  # or "degree"
    normalize: str = "n"  # or "total"
    birth: str = "uniform"  # or "per_vertex"
    on_no_live: str = "lose"  # or "stay", "stop_here"
    max_steps: int = 200
    counters: bool = True
    #: Walkers up to which they are broadcast.
    broadcast: int = 2_000_000
    rng: Rng = field(default_factory=Rng)


@dataclass
class WalkResult:
    tally: DataFrame
    steps: list[dict]
    cached: list[DataFrame] = field(default_factory=list)

    def release(self) -> None:
        """Frees the cached walkers; the tally can still be computed, from its start."""
        for d in self.cached:
            d.unpersist()


def birth_uniform(verts: DataFrame | None, n_walkers: int, rng: Rng, n: int | None = None, index: DataFrame | None = None) -> DataFrame:
    """(walker, id): each walker draws a vertex, all alike. index: dense indices (id, idx) if there are any yet."""
    at = indexed(verts, rng) if index is None else index
    n = at.count() if n is None else n
    w = at.sparkSession.range(n_walkers).select(F.col("id").alias("walker")).withColumn("idx", rng.draw("b", 0, "walker") % max(n, 1))
    return small(w, n_walkers).join(at, "idx").select("walker", "id")


def birth_per_vertex(verts: DataFrame, n_walkers: int, rng: Rng, n: int) -> DataFrame:
    """(id, k): each vertex draws Binomial(n_walkers, 1/n), keyed by its hash; the total is random."""
    return _binomial(verts.select("id", F.lit(n_walkers).alias("k"), F.lit(1.0 / n).alias("p"), rng.draw("b", 1, "id").alias("key")), "id", "k", portable=rng.kind == "portable").where("k > 0")


def birth_in_parts(verts: DataFrame, n_walkers: int, rng: Rng, buckets: int = 64) -> DataFrame:
    """(walker, id): birth_uniform() in each part of vertices 'part|vertex' by itself, with indices as indexed() gives them."""
    b = verts.select("id", F.substring_index("id", "|", 1).alias("part"), (rng.draw("v", 0, "id") % buckets).alias("bucket"))
    sizes = b.groupBy("part", "bucket").agg(F.count("*").alias("c"))
    offsets = sizes.select("part", "bucket", (F.sum("c").over(W.partitionBy("part").orderBy("bucket")) - F.col("c")).alias("offset"))
    at = b.join(offsets, ["part", "bucket"]).select("part", "id", (F.col("offset") + F.row_number().over(W.partitionBy("part", "bucket").orderBy("id")) - 1).alias("idx"))
    w = sizes.groupBy("part").agg(F.sum("c").alias("n")).crossJoin(F.broadcast(verts.sparkSession.range(n_walkers).select(F.col("id").alias("walker"))))
    return w.select("part", "walker", (rng.draw("b", 0, "walker") % F.col("n")).alias("idx")).join(at, ["part", "idx"]).select("walker", "id")


def birth_seeded(seeds: DataFrame, n_walkers: int, rng: Rng) -> DataFrame:
    """(walker, id): walkers draw from a given set of vertices (id) instead of from all."""
    return birth_uniform(seeds.select("id").distinct(), n_walkers, rng)


def lives(spark: SparkSession, n_walkers: int, stop_rate: float, horizon: int, rng: Rng) -> DataFrame:
    """(walker, life): the number of moves each walker will make, drawn once; the law of stopping step by step.

    The draw is compared with integer thresholds of the geometric law, so no logarithm is involved.
    """
    u = rng.draw("l", 0, "id")
    life = F.lit(0)
    for step in range(1, horizon + 1):
        life = life + F.when(u < F.lit(int((1 - stop_rate) ** step * (1 << 60))), 1).otherwise(0)
    return spark.range(n_walkers).select(F.col("id").alias("walker"), life.cast("int").alias("life"))


def combine(arrivals: DataFrame, who: str = "id") -> DataFrame:
    """(id, k): merged walkers; partial sums are taken before the shuffle."""
    return arrivals.groupBy(F.col(who).alias("id")).agg(F.sum("k").cast("long").alias("k"))


def thin(walkers: DataFrame, stop_rate: float, step: int, rng: Rng) -> DataFrame:
    """(id, k, stopped): how many of each vertex's k walkers stop; narrow, in counts."""
    falls = F.size(F.filter(F.sequence(F.lit(1).cast("long"), F.col("k")), lambda j: rng.draw("d", step, F.col("id"), j) < F.lit(int(stop_rate * (1 << 60)))))
    return walkers.where("k > 0").select("id", "k", falls.cast("long").alias("stopped"))


def _binomial(rows: DataFrame, *keep: str, portable: bool = False) -> DataFrame:
    """rows (.., k, p, key) with k replaced by a draw of Binomial(k, p), seeded by key; portable: by inversion, which other engines can repeat (kp under 500)."""
    if portable:
        u, k, p = F.col("key") / F.lit(float(1 << 60)), F.col("k").cast("double"), F.least(F.lit(1.0), F.col("p"))
        most = F.least(k, F.ceil(k * p + 20 * F.sqrt(k * p) + 40)).cast("int")
        # (places below the draw, the place's own share, the shares so far)
        begin = F.struct(F.lit(0).cast("long").alias("n"), F.pow(1 - p, k).alias("f"), F.pow(1 - p, k).alias("s"))
        # a step adds a place while the shares so far don't exceed the draw
        grow = lambda a, j: F.when(a["s"] > u, a).otherwise(F.struct((a["n"] + 1).alias("n"), (a["f"] * (k - j + 1) / j * p / (1 - p)).alias("f"), (a["s"] + a["f"] * (k - j + 1) / j * p / (1 - p)).alias("s")))
        drawn = F.when(p >= 1, F.col("k").cast("long")).otherwise(F.aggregate(F.sequence(F.lit(1), F.greatest(most, F.lit(1))), begin, grow)["n"])
        return rows.withColumn("k", F.least(drawn, F.col("k").cast("long"))).select(*keep)
    schema = rows.select(*keep).schema
    names = schema.names

    def work(batches):
        for b in batches:
            k, p, key = (b.column(c).to_numpy(zero_copy_only=False) for c in ("k", "p", "key"))
            got = np.array([np.random.Generator(np.random.Philox(int(s) & ((1 << 63) - 1))).binomial(int(a), min(1.0, float(q))) for a, q, s in zip(k, p, key)], dtype=np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(got) if c == "k" else b.column(c) for c in names], names=names)

    kinds = dict(rows.dtypes)
    return rows.mapInArrow(work, ", ".join(f"{c} bigint" if c == "k" else f"{c} {kinds[c]}" for c in names))


def split_shares(alive: DataFrame, live: DataFrame, step: int, rng: Rng, rounding: str = "ceil", weight: str = "equal") -> DataFrame:
    """(src, shard, k): how many of a vertex's walkers each refreshed replica gets. Narrow: arrays, no shuffle.

    alive (src, k) with live's (reps) beside it: `live` is the directory joined with alive. equal: ceil(k / m) to the first
    min(k, m) replicas in drawn order, or, "exact", k div m and one more to the first k mod m. degree: as many as a
    replica's share of live edges says, by largest prefix, so that all edges fare alike.
    """
    rows = live if alive is None else alive.join(live, "src")
    order = F.array_sort(F.transform("reps", lambda r: F.struct(rng.draw("o", step, F.col("src"), r["shard"]).alias("h"), r["shard"].alias("shard"), r["d_local"].alias("d_local"))))
    rows = rows.withColumn("o", order).withColumn("m", F.size("o").cast("long")).where("m > 0")
    if weight == "degree":
        total = F.aggregate("o", F.lit(0).cast("long"), lambda s, r: s + r["d_local"])
        upto = lambda i: F.aggregate(F.slice("o", 1, i), F.lit(0).cast("long"), lambda s, r: s + r["d_local"])
        rows = rows.withColumn("t", total).select("src", "k", "t", F.posexplode("o").alias("i", "r"), "o")
        share = F.floor(F.col("k") * upto(F.col("i") + 1) / F.col("t")) - F.floor(F.col("k") * upto(F.col("i")) / F.col("t"))
    else:
        rows = rows.select("src", "k", "m", F.posexplode("o").alias("i", "r"))
        if rounding == "ceil":
            share = F.when(F.col("i") < F.least("k", "m"), F.ceil(F.col("k") / F.col("m")))
        else:
            share = F.expr("k div m") + F.when(F.col("i") < F.col("k") % F.col("m"), 1).otherwise(0)
    return rows.select("src", "r.shard", share.cast("long").alias("k")).where("k > 0")


def pick_in_replica(shares: DataFrame, replicas: DataFrame, step: int, rng: Rng) -> DataFrame:
    """(id, k): each walker picks one of its replica's neighbours; the neighbour arrays stay where they are."""
    met = shares.join(replicas.select("src", "shard", "nbrs", "d_local"), ["src", "shard"])
    gone = met.select("src", "shard", "nbrs", "d_local", F.explode(F.sequence(F.lit(1).cast("long"), F.col("k"))).alias("j"))
    return combine(gone.select(F.element_at("nbrs", (1 + rng.draw("p", step, "src", "shard", "j") % F.col("d_local")).cast("int")).alias("id"), F.lit(1).alias("k")))


def pick_by_source(shares: DataFrame, replicas: DataFrame, step: int, rng: Rng) -> DataFrame:
    """pick_in_replica() for replicas that are bucketed by src: shares meet them by src alone, so that only shares move."""
    lists = shares.groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("shard", "k"))).alias("ks"))
    met = lists.hint("merge").join(replicas.select("src", "shard", "nbrs", "d_local"), "src").withColumn("k", F.element_at("ks", F.col("shard"))).where("k > 0")
    gone = met.select("src", "shard", "nbrs", "d_local", F.explode(F.sequence(F.lit(1).cast("long"), F.col("k"))).alias("j"))
    return combine(gone.select(F.element_at("nbrs", (1 + rng.draw("p", step, "src", "shard", "j") % F.col("d_local")).cast("int")).alias("id"), F.lit(1).alias("k")))


def scatter_binomial(alive_live: DataFrame, replicas: DataFrame, p_s: float, step: int, rng: Rng, unbiased: bool = False) -> DataFrame:
    """(id, k): each live edge of a vertex with k walkers gets Binomial(k, p); totals aren't kept exactly.

    p = min(1, 1 / (d p_s)), or, unbiased, 1 / (d p_s + (1 - p_s)^d), right where one edge at least is live.
    """
    d = F.col("d_out")
    p = 1 / (d * p_s + F.pow(F.lit(1 - p_s), d)) if unbiased else F.least(F.lit(1.0), 1 / (d * p_s))
    edges = alive_live.select("src", "k", "d_out", F.explode("reps").alias("r")).select("src", "k", "d_out", "r.shard").join(replicas.select("src", "shard", "nbrs"), ["src", "shard"])
    rows = edges.select(F.explode("nbrs").alias("id"), "k", p.alias("p"), "src").withColumn("key", rng.draw("n", step, "src", "id"))
    return combine(_binomial(rows, "id", "k", portable=rng.kind == "portable").where("k > 0"))


def _united(parts: list[DataFrame]) -> DataFrame:
    """(id, c): the sum of tallies, without zeros."""
    out = parts[0]
    for d in parts[1:]:
        out = out.unionByName(d)
    return out.groupBy("id").agg(F.sum("c").cast("long").alias("c")).where("c > 0")


def walker_tally(layout: Layout, params: WalkParams, births: DataFrame | None = None) -> WalkResult:
    """Tally (id, c) and, per step, counters (walkers in, stopped, refreshes tried and sent, signals, walkers out)."""
    p, rng = params, params.rng
    born = births is not None
    if births is None:
        if p.birth == "uniform":
            births = birth_uniform(None, p.n_walkers, rng, layout.n, layout.index).groupBy("id").agg(F.count("*").alias("k"))
        else:
            births = birth_per_vertex(layout.vertices, p.n_walkers, rng, layout.n)
    cached: list[DataFrame] = []

    def keep(df: DataFrame) -> DataFrame:
        cached.append(df.persist())
        return df

    walkers = keep(births)
    if p.birth != "uniform" or born:
        # births that are drawn or given may be more than asked for: the bound is of what there is
        rows = walkers.count()
        p = replace(p, n_walkers=max(p.n_walkers, rows))
    done: list[DataFrame] = []
    steps: list[dict] = []
    last = p.horizon if p.horizon is not None else p.max_steps
    for step in range(last):
        thinned = keep(thin(walkers, p.stop_rate, step, rng))
        done.append(thinned.select("id", F.col("stopped").alias("c")))
        alive = thinned.where("k > stopped").select(F.col("id").alias("src"), (F.col("k") - F.col("stopped")).alias("k"))
        replicas, directory = (layout.replicas, layout.directory) if layout.near is None else layout.near(small(alive, p.n_walkers, p.broadcast))
        met = small(alive, p.n_walkers, p.broadcast).join(directory, "src").withColumn("had", F.size("reps"))
        live = live_replicas(met.select("src", "k", "d_out", "reps", "had"), p.refresh_rate, step, rng, p.erasure == "at_least_one")
        if p.scatter == "split":
            shares = split_shares(None, live, step, rng, p.rounding, p.replica_weight)
            if layout.bucketed and p.n_walkers > p.broadcast:
                arrived = pick_by_source(shares, replicas, step, rng)
            else:
                arrived = pick_in_replica(small(shares, p.n_walkers, p.broadcast), replicas, step, rng)
        else:
            arrived = scatter_binomial(live, replicas, p.refresh_rate, step, rng, p.scatter == "binomial_unbiased")
        if p.erasure != "at_least_one" and p.refresh_rate < 1 and p.on_no_live != "lose":
            stuck = live.where(F.size("reps") == 0).select(F.col("src").alias("id"), "k")
            if p.on_no_live == "stay":
                arrived = combine(arrived.unionByName(stuck))
            else:
                done.append(keep(stuck.select("id", F.col("k").alias("c"))))
        ends = step % EVERY == EVERY - 1
        walkers = cut(arrived) if ends else keep(arrived)
        if p.counters:
            a = thinned.agg(F.sum("k"), F.sum("stopped"), F.count_if(F.col("k") > F.col("stopped"))).first()
            b = live.agg(F.sum("had"), F.sum(F.size("reps"))).first()
            c = walkers.agg(F.count("*"), F.coalesce(F.sum("k"), F.lit(0))).first()
            steps.append({"step": step, "alive_in": a[0] or 0, "stopped": a[1] or 0, "active": a[2] or 0, "refresh_tried": b[0] or 0, "refresh_sent": b[1] or 0, "destinations": c[0], "alive_out": c[1]})
        if ends and step < last - 1:  # so that a long walk's plan and cache stay as small as a short one's
            done = [cut(_united(done))]
            while cached:
                cached.pop().unpersist()
        if p.horizon is None and (steps[-1]["destinations"] == 0 if p.counters else ends and walkers.isEmpty()):
            break
    done.append(walkers.select("id", F.col("k").alias("c")))
    return WalkResult(_united(done), steps, cached)


def estimate(tally: DataFrame, n_walkers: int, normalize: str = "n") -> DataFrame:
    """(id, value): shares of walkers, of those sent out ("n") or of those counted ("total")."""
    if normalize == "n":
        return tally.select("id", (F.col("c") / F.lit(n_walkers)).alias("value"))
    return tally.crossJoin(F.broadcast(tally.agg(F.sum("c").alias("all")))).select("id", (F.col("c") / F.col("all")).alias("value"))


def top_k(rank: DataFrame, k: int, pad: DataFrame | None = None) -> DataFrame:
    """(position, id, value): the k heaviest, ties by id; pad (id) fills up with vertices of no weight."""
    if pad is not None:
        rank = rank.unionByName(pad.join(rank, "id", "left_anti").select("id", F.lit(0.0).alias("value")))
    top = rank.orderBy(F.desc(F.round("value", 12)), "id").limit(k)
    return top.withColumn("position", F.row_number().over(W.orderBy(F.desc(F.round("value", 12)), "id"))).select("position", "id", "value")


# --- walkers with identity: the processes that the analysis is about ---


def out_lists(edges: DataFrame) -> DataFrame:
    """(src, nbrs, d): sorted out-neighbours."""
    return edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).withColumn("d", F.size("nbrs"))


def _live(lists: DataFrame, p_s: float, step: int, rng: Rng, *more: str) -> DataFrame:
    """lists (src, nbrs, .., *more) with `live`: the neighbours whose edges aren't erased in this step, one at least."""
    if p_s >= 1:
        return lists.withColumn("live", F.col("nbrs"))
    extra = [F.col(m) for m in more]
    kept = F.filter("nbrs", lambda v: rng.draw("e", step, F.col("src"), v, *extra) < F.lit(int(p_s * (1 << 60))))
    one = F.array(F.element_at("nbrs", (1 + rng.draw("f", step, F.col("src"), *extra) % F.col("d")).cast("int")))
    return lists.withColumn("kept", kept).withColumn("live", F.when(F.size("kept") > 0, F.col("kept")).otherwise(one)).drop("kept")


def identity_step(pos: DataFrame, lists: DataFrame, p_s: float, step: int, rng: Rng, how: str = "live") -> DataFrame:
    """(walker, id, blocked): one move of every walker of pos (walker, id).

    live: each walks along a live edge, all alike; walkers of a vertex share its erased edges. serial: each walker has
    erased edges of its own. blocking: draws among all edges; on an erased one, draws again among the live ones.
    """
    met = pos.withColumnRenamed("id", "src").join(lists, "src")
    rows = _live(met, p_s, step, rng, *(["walker"] if how == "serial" else []))
    at = lambda a, purpose: F.element_at(a, (1 + rng.draw(purpose, step, "walker") % F.size(a)).cast("int"))
    if how != "blocking":
        return rows.select("walker", at("live", "p").alias("id"), F.lit(False).alias("blocked"))
    first = rows.withColumn("first", at("nbrs", "p")).withColumn("blocked", ~F.array_contains("live", F.col("first")))
    return first.select("walker", F.when(F.col("blocked"), at("live", "q")).otherwise(F.col("first")).alias("id"), "blocked")


def identity_walk(edges: DataFrame, n_walkers: int, horizon: int, stop_rate: float, p_s: float, rng: Rng = Rng(), how: str = "live", death: str = "each_step") -> DataFrame:
    """(walker, id, step, stopped, blocked): where each walker is before each step, and where and when it stopped.

    death: drawn in "each_step", or "at_birth": each walker's life() is drawn once, and it stops when that is over.
    """
    span = lives(edges.sparkSession, n_walkers, stop_rate, horizon, rng) if death == "at_birth" else None
    lists = cut(out_lists(edges))
    pos = birth_uniform(lists.select(F.col("src").alias("id")), n_walkers, rng).withColumn("blocked", F.lit(False))
    out = None
    for step in range(horizon + 1):
        end = rng.happens(stop_rate, "d", step, "walker") if step < horizon else F.lit(True)
        if span is not None:
            pos, end = pos.join(small(span, n_walkers), "walker"), F.col("life") <= step
        now = cut(pos.select("walker", "id", F.lit(step).alias("step"), end.alias("stopped"), "blocked"))
        out = now if out is None else out.unionByName(now)
        if step < horizon:
            pos = identity_step(now.where("not stopped").select("walker", "id"), lists, p_s, step, rng, how)
    return out


def teleport_walk(edges: DataFrame, n_walkers: int, horizon: int, stop_rate: float, rng: Rng = Rng()) -> DataFrame:
    """(id, c): walkers that move `horizon` times and, with probability stop_rate a move, jump to a vertex at random."""
    lists = cut(out_lists(edges))
    at = cut(indexed(lists.select(F.col("src").alias("id")), rng))
    n = at.count()
    pos = cut(birth_uniform(lists.select(F.col("src").alias("id")), n_walkers, rng, n))
    for step in range(horizon):
        jump = rng.happens(stop_rate, "d", step, "walker")
        flagged = pos.withColumn("jump", jump)
        moved = identity_step(flagged.where("not jump").select("walker", "id"), lists, 1.0, step, rng).select("walker", "id")
        jumped = flagged.where("jump").select("walker", (rng.draw("t", step, "walker") % n).alias("idx")).join(at, "idx").select("walker", "id")
        pos = cut(moved.unionByName(jumped))
    return pos.groupBy("id").agg(F.count("*").alias("c"))


# --- the host abstraction ---


@dataclass
class VertexProgram:
    """init(layout) -> state (id, ..); apply(state, step) -> (state, messages (src, ..)); refresh(live (src, .., reps), step) -> live;
    scatter(live, replicas, step) -> state."""

    init: Callable[[Layout], DataFrame]
    apply: Callable[[DataFrame, int], tuple[DataFrame | None, DataFrame]]
    scatter: Callable[[DataFrame, DataFrame, int], DataFrame]
    refresh: Callable[[DataFrame, int], DataFrame] = lambda live, step: live
    finish: Callable[[list[DataFrame], DataFrame], DataFrame] = lambda kept, state: state


def run(program: VertexProgram, layout: Layout, steps: int) -> DataFrame:
    state = cut(program.init(layout))
    kept: list[DataFrame] = []
    for step in range(steps):
        own, messages = program.apply(state, step)
        if own is not None:
            kept.append(own)
        live = program.refresh(messages.join(layout.directory, "src"), step)
        state = cut(program.scatter(live, layout.replicas, step))
    return program.finish(kept, state)


def walker_program(p: WalkParams) -> VertexProgram:
    """The walker-tally method on run()."""
    def apply(state: DataFrame, step: int):
        t = cut(thin(state, p.stop_rate, step, p.rng))
        return t.select("id", F.col("stopped").alias("c")), t.where("k > stopped").select(F.col("id").alias("src"), (F.col("k") - F.col("stopped")).alias("k"))

    def finish(kept: list[DataFrame], state: DataFrame) -> DataFrame:
        out = state.select("id", F.col("k").alias("c"))
        for d in kept:
            out = out.unionByName(d)
        return out.groupBy("id").agg(F.sum("c").cast("long").alias("c")).where("c > 0")

    return VertexProgram(
        init=lambda lay: birth_uniform(lay.vertices, p.n_walkers, p.rng, lay.n).groupBy("id").agg(F.count("*").alias("k")),
        apply=apply,
        refresh=lambda live, step: live_replicas(live, p.refresh_rate, step, p.rng, p.erasure == "at_least_one"),
        scatter=lambda live, reps, step: pick_in_replica(split_shares(None, live, step, p.rng, p.rounding, p.replica_weight), reps, step, p.rng),
        finish=finish,
    )


def power_program(layout: Layout, p_t: float = 0.15) -> VertexProgram:
    """Power iteration on run(): each vertex sends its value over its degree to all neighbours, on the same replicas that walkers use."""
    verts = layout.vertices

    def scatter(live: DataFrame, replicas: DataFrame, step: int) -> DataFrame:
        sent = live.select("src", (F.col("value") / F.col("d_out")).alias("share")).join(replicas.select("src", "nbrs"), "src")
        got = sent.select(F.explode("nbrs").alias("id"), "share").groupBy("id").agg(F.sum("share").alias("m"))
        return verts.join(got, "id", "left").select("id", (F.coalesce("m", F.lit(0.0)) * (1 - p_t) + p_t / max(layout.n, 1)).alias("value"))

    return VertexProgram(
        init=lambda lay: lay.vertices.select("id", F.lit(1.0 / max(lay.n, 1)).alias("value")),
        apply=lambda state, step: (None, state.select(F.col("id").alias("src"), "value")),
        scatter=scatter,
    )


def gate(messages: DataFrame, directory: DataFrame, p_s: float, step: int, rng: Rng = Rng()) -> DataFrame:
    """messages (src, ..) on the replicas that are refreshed in this step: (src, .., shard). Any step in which a vertex picks
    a few neighbours at random can be gated so; p_s = 1 turns the gate off."""
    live = live_replicas(messages.join(directory, "src"), p_s, step, rng)
    return live.withColumn("shard", F.explode("reps.shard")).drop("reps", "d_out")


def gossip(seeds: DataFrame, layout: Layout, rounds: int, p_s: float, rng: Rng = Rng()) -> DataFrame:
    """(id, round): a rumour goes, each round, from all who know it to one neighbour in each refreshed replica."""
    known = cut(seeds.select("id", F.lit(0).alias("round")))
    for r in range(rounds):
        told = gate(known.select(F.col("id").alias("src")), layout.directory, p_s, r, rng).join(layout.replicas, ["src", "shard"])
        heard = told.select(F.element_at("nbrs", (1 + rng.draw("g", r, "src", "shard") % F.col("d_local")).cast("int")).alias("id"), F.lit(r + 1).alias("round"))
        known = cut(known.unionByName(heard).groupBy("id").agg(F.min("round").alias("round")))
    return known


def with_params(p: WalkParams, **more) -> WalkParams:
    return replace(p, **more)
