"""DuckDB SQL that repeats the methods, draw by draw, for small graphs."""

from __future__ import annotations

from walkrank.functions.rng import Rng, threshold

RNG = Rng()
P_T = 0.15

GRAPHS = {
    "toy": "SELECT * FROM (VALUES ('a','b'),('a','c'),('b','c'),('c','a'),('d','a'),('d','c')) AS t(src, dst)",
    "trade": """SELECT DISTINCT e.src, e.dst FROM (SELECT unnest([{'src': 'c' || o_custkey, 'dst': 'p' || l_partkey}, {'src': 'p' || l_partkey, 'dst': 's' || l_suppkey},
        {'src': 's' || l_suppkey, 'dst': 'c' || o_custkey}]) AS e FROM lineitem JOIN orders ON l_orderkey = o_orderkey)""",
    "activity": "SELECT DISTINCT 'u' || user_id AS src, 'u' || nxt AS dst FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL AND nxt <> user_id",
    "customers": """SELECT DISTINCT 'c' || o_custkey AS src, 'c' || nxt AS dst FROM (SELECT o_custkey, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey, l_linenumber) AS nxt
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey) WHERE nxt IS NOT NULL AND nxt <> o_custkey""",
    "mixed": """SELECT DISTINCT week || '|u' || src AS src, week || '|u' || dst AS dst FROM (WITH e AS (SELECT user_id, event_id, ts, strftime(date_trunc('week', ts), '%Y-%m-%d') AS week FROM events),
        c AS (SELECT o_custkey AS src, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey, l_linenumber) AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey)
        SELECT week, user_id AS src, lead(user_id) OVER (PARTITION BY week, date_trunc('day', ts) ORDER BY ts, event_id) AS dst FROM e UNION ALL SELECT week, src, dst FROM (SELECT DISTINCT week FROM e) CROSS JOIN (SELECT DISTINCT src, dst FROM c)) WHERE dst IS NOT NULL AND src <> dst""",
    "links": "SELECT DISTINCT 'n' || page_id AS src, 'u' || href AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)",
    "similarity": """SELECT src, dst FROM (SELECT 'v' || a.vec_id AS src, 'v' || b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_inner_product(a.e, b.e)
        / (sqrt(list_inner_product(a.e, a.e)) * sqrt(list_inner_product(b.e, b.e))), 9) DESC, b.vec_id) AS r
        FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE r <= 8""",
    "sentences": r"""SELECT 'd_' || doc_id || '_' || p1 AS src, 'd_' || doc_id || '_' || p2 AS dst FROM (WITH l AS (SELECT doc_id, unnest(range(0, len(string_split(text, chr(10))))) AS pos, unnest(string_split(text, chr(10))) AS line FROM documents),
        w AS (SELECT doc_id, pos, unnest(list_distinct(list_filter(string_split_regex(lower(line), '[^\p{L}]+'), lambda x: length(x) >= 3))) AS w FROM l)
        SELECT a.doc_id, a.pos AS p1, b.pos AS p2 FROM w a JOIN w b ON a.doc_id = b.doc_id AND a.w = b.w AND a.pos <> b.pos GROUP BY ALL HAVING count(*) >= 2)""",
}


def next_words_sql(table: str, where: str = "true", window: int = 1) -> str:
    pairs = " UNION ALL ".join(f"SELECT a[i] AS src, a[i + {k}] AS dst FROM (SELECT a, unnest(range(1, len(a) + 1 - {k})) AS i FROM t)" for k in range(1, window + 1))
    return rf"""SELECT DISTINCT src, dst FROM (WITH t AS (SELECT list_filter(string_split_regex(lower(text), '[^\p{{L}}]+'), lambda w: length(w) >= 3) AS a FROM {table} WHERE {where}) {pairs}) WHERE src <> dst"""


GRAPHS |= {
    "words": next_words_sql("documents"), "words_w3": next_words_sql("documents", window=3), "items": next_words_sql("benchmark"), "turns": next_words_sql("conversations", "role = 'user'"),
    **{f"words_{x}": next_words_sql("documents", f"lang = '{x}'") for x in ("en", "de", "fr", "es")},
}


def graph(name: str, repair: str = "self_loop") -> str:
    """CTEs g (edges as built), edges (repaired), v (vertices)."""
    more = {
        "self_loop": "SELECT src, dst FROM g UNION ALL SELECT DISTINCT dst, dst FROM g WHERE dst NOT IN (SELECT src FROM g)",
        "reverse_edge": "SELECT src, dst FROM g UNION SELECT dst, src FROM g WHERE dst NOT IN (SELECT src FROM g)",
        "none": "SELECT src, dst FROM g",
    }[repair]
    return f"g AS MATERIALIZED ({GRAPHS[name]}), edges AS MATERIALIZED ({more}), v AS MATERIALIZED (SELECT src AS id FROM edges UNION SELECT dst FROM edges)"


def ranks(iterations: int, p_t: float = P_T, edges: str = "edges", degrees: str | None = None, to_all: bool = False) -> str:
    """CTEs r0..r(iterations) (id, value)."""
    out = [f"ed AS MATERIALIZED (SELECT e.src, e.dst, d.d FROM {edges} e JOIN (SELECT src, count(*) AS d FROM {degrees or edges} GROUP BY src) d USING (src))", "r0 AS (SELECT id, 1.0 / (SELECT count(*) FROM v)::DOUBLE AS value FROM v)"]
    for i in range(iterations):
        lost = f" + (SELECT coalesce(sum(value), 0) FROM r{i} WHERE id NOT IN (SELECT src FROM {edges})) / (SELECT count(*) FROM v)" if to_all else ""
        out.append(f"m{i} AS (SELECT dst AS id, sum(value / d) AS m FROM ed JOIN r{i} ON src = id GROUP BY dst)")
        out.append(f"r{i + 1} AS MATERIALIZED (SELECT v.id, (coalesce(m, 0){lost}) * (1 - {p_t}::DOUBLE) + {p_t}::DOUBLE / (SELECT count(*) FROM v) AS value FROM v LEFT JOIN m{i} USING (id))")
    return ", ".join(out)


def exact(iterations: int = 200, p_t: float = P_T, degrees: bool = False) -> str:
    """CTEs up to rx (id, value), so many iterations by recursion; degrees: ed isn't there yet. Needs WITH RECURSIVE."""
    ed = "ed AS MATERIALIZED (SELECT e.src, e.dst, d.d FROM edges e JOIN (SELECT src, count(*) AS d FROM edges GROUP BY src) d USING (src)), " if degrees else ""
    return f"""{ed}it(i, id, value) AS (SELECT 0, id, 1.0::DOUBLE / (SELECT count(*) FROM v)::DOUBLE FROM v UNION ALL SELECT (SELECT max(i) FROM it) + 1, v.id, coalesce(m, 0) * (1 - {p_t}::DOUBLE) + {p_t}::DOUBLE / (SELECT count(*) FROM v)
        FROM v LEFT JOIN (SELECT dst AS id, sum(value / d) AS m FROM ed JOIN it ON src = id GROUP BY dst) q USING (id) WHERE (SELECT max(i) FROM it) < {iterations}), rx AS MATERIALIZED (SELECT id, value FROM it WHERE i = {iterations})"""


def binomial(rows: str, keep: str) -> str:
    """keep and kb, a draw of Binomial(k, p) by inversion, for rows (keep.., k, p, key)."""
    logs = "lgamma(k + 1) - lgamma(j + 1) - lgamma(k - j + 1) + j * ln(p) + (k - j) * ln(1 - p)"
    return f"""SELECT {keep}, CASE WHEN p >= 1 THEN k ELSE least(k, below) END::BIGINT AS kb FROM (SELECT {keep}, k, p, key, count(*) FILTER (cdf <= key / {float(1 << 60)}::DOUBLE) AS below FROM (
        SELECT {keep}, k, p, key, j, sum(CASE WHEN p >= 1 THEN 0 ELSE exp({logs}) END) OVER (PARTITION BY {keep} ORDER BY j) AS cdf FROM (SELECT {keep}, k, p, key, unnest(range(0, least(k, ceil(k * least(1, p) + 20 * sqrt(k * least(1, p)) + 40))::BIGINT + 1)) AS j FROM ({rows}))) GROUP BY ALL)"""


def index() -> str:
    return f"idx AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY {RNG.sql('v', 0, 'id')} % 64, id) - 1 AS ix FROM v)"


def births(n: int, of: str = "idx") -> str:
    return f"born AS MATERIALIZED (SELECT w AS walker, id FROM (SELECT w, {RNG.sql('b', 0, 'w')} % (SELECT count(*) FROM {of}) AS ix FROM (SELECT unnest(range({n})) AS w)) JOIN {of} USING (ix))"


def shard(kind: str, shards: int, chunk: int) -> str:
    rows = max(1, int(shards**0.5))
    cols = max(1, shards // rows)
    return {
        "random": f"{RNG.sql('y', 0, 'src', 'dst')} % {shards}",
        "grid": f"({RNG.sql('y', 1, 'src')} % {rows}) * {cols} + {RNG.sql('y', 2, 'dst')} % {cols}",
        "source": f"{RNG.sql('y', 3, 'src')} % {shards}",
        "chunked": f"{RNG.sql('y', 4, 'src', 'dst')} % ((count(*) OVER (PARTITION BY src) + {chunk} - 1) // {chunk})",
    }[kind]


def replicas(kind: str = "random", shards: int = 8, chunk: int = 16) -> str:
    return f"rep AS MATERIALIZED (SELECT src, shard, list(dst ORDER BY dst) AS nbrs, count(*) AS d_local FROM (SELECT src, dst, {shard(kind, shards, chunk)} AS shard FROM edges) GROUP BY src, shard)"


def live(step: int, alive: str, p_s: float, force: bool = True) -> str:
    """CTEs lv{step}: replicas of alive's vertices (src, k) that are refreshed."""
    met = f"mt{step} AS MATERIALIZED (SELECT a.src, a.k, r.shard, r.d_local, row_number() OVER (PARTITION BY a.src ORDER BY r.shard) AS rn, count(*) OVER (PARTITION BY a.src) AS n, "
    met += (f"{RNG.sql('r', step, 'a.src', 'r.shard')} < {threshold(p_s)}" if p_s < 1 else "true") + f" AS on_ FROM {alive} a JOIN rep r ON a.src = r.src)"
    forced = f" UNION ALL SELECT src, k, shard, d_local FROM mt{step} WHERE src NOT IN (SELECT src FROM mt{step} WHERE on_) AND rn = 1 + {RNG.sql('f', step, 'src')} % n" if force else ""
    return f"{met}, lv{step} AS MATERIALIZED (SELECT src, k, shard, d_local FROM mt{step} WHERE on_{forced})"


def shares(step: int, rounding: str = "ceil", weight: str = "equal") -> str:
    order = f"PARTITION BY src ORDER BY {RNG.sql('o', step, 'src', 'shard')}, shard"
    if weight == "degree":
        x = f"SELECT src, shard, (k * upto // t) - (k * (upto - d_local) // t) AS k FROM (SELECT *, sum(d_local) OVER ({order}) AS upto, sum(d_local) OVER (PARTITION BY src) AS t FROM lv{step})"
    else:
        give = "CASE WHEN i < least(k, m) THEN (k + m - 1) // m ELSE 0 END" if rounding == "ceil" else "k // m + CASE WHEN i < k % m THEN 1 ELSE 0 END"
        x = f"SELECT src, shard, {give} AS k FROM (SELECT *, row_number() OVER ({order}) - 1 AS i, count(*) OVER (PARTITION BY src) AS m FROM lv{step})"
    return f"sh{step} AS MATERIALIZED (SELECT src, shard, k::BIGINT AS k FROM ({x}) WHERE k > 0)"


def picks(step: int) -> str:
    pick = f"nbrs[1 + {RNG.sql('p', step, 'src', 'shard', 'j')} % d_local]"
    return f"w{step + 1} AS MATERIALIZED (SELECT id, count(*) AS k FROM (SELECT {pick} AS id FROM (SELECT s.src, s.shard, r.nbrs, r.d_local, unnest(range(1, s.k + 1)) AS j FROM sh{step} s JOIN rep r ON s.src = r.src AND s.shard = r.shard)) GROUP BY id)"


def thinned(step: int, p_t: float = P_T) -> str:
    return f"""th{step} AS MATERIALIZED (SELECT id, k, (SELECT 0) + stopped AS stopped FROM (SELECT id, k, count(*) FILTER ({RNG.sql('d', step, 'id', 'j')} < {threshold(p_t)}) AS stopped
        FROM (SELECT id, k, unnest(range(1, k + 1)) AS j FROM w{step}) GROUP BY id, k)), al{step} AS (SELECT id AS src, k - stopped AS k FROM th{step} WHERE k > stopped)"""


def tally(name: str, n: int, t: int, p_s: float = 1.0, rounding: str = "ceil", weight: str = "equal", kind: str = "random", shards: int = 8, force: bool = True, seeded: str | None = None) -> str:
    """CTEs up to tally (id, c)."""
    parts = [graph(name), replicas(kind, shards), index()]
    if seeded:
        parts += [f"sidx AS (SELECT id, row_number() OVER (ORDER BY {RNG.sql('v', 0, 'id')} % 64, id) - 1 AS ix FROM v WHERE {seeded})"]
    parts += [births(n, "sidx" if seeded else "idx"), "w0 AS MATERIALIZED (SELECT id, count(*) AS k FROM born GROUP BY id)"]
    for s in range(t):
        parts += [thinned(s), live(s, f"al{s}", p_s, force), shares(s, rounding, weight), picks(s)]
    ends = " UNION ALL ".join([f"SELECT id, stopped AS c FROM th{s}" for s in range(t)] + [f"SELECT id, k FROM w{t}"])
    return ", ".join(parts + [f"tally AS MATERIALIZED (SELECT id, sum(c)::BIGINT AS c FROM ({ends}) GROUP BY id HAVING sum(c) > 0)"])


def identity(name: str, n: int, t: int, p_s: float, how: str = "live", p_t: float = P_T, at_birth: bool = False) -> str:
    """CTEs up to pos (walker, id, step, stopped, blocked)."""
    more = ["walker"] if how == "serial" else []
    parts = [graph(name), index(), births(n), "ls AS MATERIALIZED (SELECT src, list(dst ORDER BY dst) AS nbrs, count(*) AS d FROM edges GROUP BY src)", "p0 AS (SELECT walker, id, false AS blocked FROM born)"]
    for s in range(t + 1):
        end = f"{RNG.sql('d', s, 'walker')} < {threshold(p_t)}" if s < t else "true"
        if at_birth:  # as many moves as the one draw says
            end = (f"{RNG.sql('l', 0, 'walker')} >= {int((1 - p_t) ** (s + 1) * (1 << 60))}") if s < t else "true"
        parts.append(f"q{s} AS MATERIALIZED (SELECT walker, id, {s} AS step, {end} AS stopped, blocked FROM p{s})")
        if s == t:
            break
        if p_s < 1:
            kept = f"list_filter(nbrs, lambda x: {RNG.sql('e', s, 'src', 'x', *more)} < {threshold(p_s)})"
            lv = f"CASE WHEN len({kept}) > 0 THEN {kept} ELSE [nbrs[1 + {RNG.sql('f', s, 'src', *more)} % d]] END"
        else:
            lv = "nbrs"
        parts.append(f"x{s} AS MATERIALIZED (SELECT walker, nbrs, d, {lv} AS live FROM q{s} JOIN ls ON id = src WHERE NOT stopped)")
        p, q = RNG.sql("p", s, "walker"), RNG.sql("q", s, "walker")
        if how == "blocking":
            parts.append(f"p{s + 1} AS (SELECT walker, CASE WHEN list_contains(live, f) THEN f ELSE live[1 + {q} % len(live)] END AS id, NOT list_contains(live, f) AS blocked FROM (SELECT *, nbrs[1 + {p} % d] AS f FROM x{s}))")
        else:
            parts.append(f"p{s + 1} AS (SELECT walker, live[1 + {p} % len(live)] AS id, false AS blocked FROM x{s})")
    return ", ".join(parts + [f"pos AS MATERIALIZED ({' UNION ALL '.join(f'SELECT * FROM q{s}' for s in range(t + 1))})"])


def top(rank: str, k: int) -> str:
    """A query for (position, vertex, score) of the k heaviest."""
    return f"SELECT row_number() OVER (ORDER BY round(value, 12) DESC, id)::INT AS position, id AS vertex, round(value, 9) AS score FROM (SELECT * FROM {rank} ORDER BY round(value, 12) DESC, id LIMIT {k})"
