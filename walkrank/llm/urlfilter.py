"""URL filters by a temporal list join, with DataFrame functions only.

A list is a table of dated entries (kind, key, action, at, category): 'add' makes a key active from `at`, 'remove'
ends it. Per key the events become validity intervals [from, until). A capture (page_id, url, fetched_at) gives
the keys that could match it: its host and all parent domains, its path prefixes, its query parameters. The as-of
join keeps the entries that were active when the capture was fetched.

A list of at most SMALL intervals, which is counted first, is broadcast, and keys that it lacks go before any exchange; beyond that, keys that many
captures share are dealt over salts on both sides. Prefixes of any depth and texts of any length are looked up.
Null or malformed URLs have no host and match nothing; a null fetch time matches nothing. At one instant removals
come before additions, so an entry that is both removed and added stays active; with several categories added
at one instant the smallest holds. Entries with a null key, time or action are ignored. Repeated captures come back
as often as they went in.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.llm.common import draw

SALTS = 32
#: Lists of at most so many intervals are broadcast.
SMALL = 200_000


def host_of(url: Column) -> Column:
    """The host in lower case, without user, port or final dot; empty if there is none."""
    place = F.regexp_extract(url, "^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1)
    return F.lower(F.regexp_replace(F.regexp_replace(F.regexp_replace(place, "^.*@", ""), ":[0-9]*$", ""), "\\.$", ""))


def path_of(url: Column) -> Column:
    return F.regexp_extract(url, "^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)", 1)


def query_of(url: Column) -> Column:
    return F.regexp_extract(url, "^[^?#]*\\?([^#]*)", 1)


def intervals(entries: DataFrame) -> DataFrame:
    """(kind, key, category, since, until): when each key was listed; until is null for entries that still are."""
    events = entries.where("kind is not null and key is not null and at is not null and action in ('add', 'remove')")
    one = events.groupBy("kind", "key", "at").agg(F.max(F.col("action") == "add").alias("on"), F.min(F.when(F.col("action") == "add", F.coalesce("category", F.lit("")))).alias("category"))
    along = W.partitionBy("kind", "key").orderBy("at")
    return one.withColumn("until", F.lead("at").over(along)).where("on").select("kind", "key", "category", F.col("at").alias("since"), "until")


def capture_keys(captures: DataFrame) -> DataFrame:
    """captures with `rule` (kind, key), one row for each key that could match, and one row of kind 'self'."""
    labels = F.split(F.col("__host"), "\\.")
    known = F.col("__host") != ""
    domains = F.expr("transform(sequence(1, size(__l)), i -> named_struct('kind', 'domain', 'key', array_join(slice(__l, i, size(__l)), '.')))")
    steps = F.expr("transform(sequence(1, size(__p)), i -> named_struct('kind', 'prefix', 'key', concat(__host, '/', array_join(slice(__p, 1, i), '/'))))")
    params = F.expr("transform(__q, x -> named_struct('kind', 'param', 'key', x))")
    none = F.expr("cast(array() as array<struct<kind:string,key:string>>)")
    own = F.array(F.struct(F.lit("self").alias("kind"), F.lit("").alias("key")))
    split = captures.withColumn("__host", F.coalesce(host_of(F.col("url")), F.lit("")))
    split = split.withColumns({
        "__l": labels,
        "__p": F.array_remove(F.split(F.coalesce(path_of(F.col("url")), F.lit("")), "/"), ""),
        "__q": F.array_distinct(F.array_remove(F.transform(F.split(F.coalesce(query_of(F.col("url")), F.lit("")), "&"), lambda x: F.lower(F.regexp_extract(x, "^([^=]*)", 1))), "")),
    })
    rules = F.concat(own, F.when(known, domains).otherwise(none), F.when(known & (F.size("__p") > 0), steps).otherwise(none), F.when(known & (F.size("__q") > 0), params).otherwise(none))
    return split.withColumn("rule", F.explode(rules)).drop("__l", "__p", "__q")


def apply_lists(captures: DataFrame, entries: DataFrame) -> DataFrame:
    """One row for each capture (page_id, url, fetched_at): host, blocked, n_rules, categories, rule (the least that matched)."""
    rows = capture_keys(captures.select("page_id", "url", "fetched_at"))
    salted = rows.select("page_id", "url", "fetched_at", "__host", F.col("rule.kind").alias("kind"), F.col("rule.key").alias("key"), F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).alias("__salt"))
    # rows of kind 'self' match nothing and would share one key: they get one each
    salted = salted.withColumn("key", F.when(F.col("kind") == "self", F.xxhash64("page_id", "url").cast("string")).otherwise(F.col("key")))
    lists = intervals(entries)
    if lists.limit(SMALL + 1).count() <= SMALL:
        # keys that no list has go before the exchange; the row of kind 'self' stays
        listed = F.broadcast(lists.select("kind", "key").distinct().withColumn("__listed", F.lit(True)))
        salted = salted.join(listed, ["kind", "key"], "left").where((F.col("kind") == "self") | F.col("__listed")).drop("__listed", "__salt")
        met = salted.join(F.broadcast(lists), ["kind", "key"], "left")
    else:
        copies = lists.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
        met = salted.join(copies, ["kind", "key", "__salt"], "left")
    active = (F.col("since") <= F.col("fetched_at")) & (F.col("until").isNull() | (F.col("fetched_at") < F.col("until")))
    name = F.concat_ws(":", "kind", "key")
    per = met.groupBy("page_id", "url", "fetched_at", F.col("__host").alias("host")).agg(
        F.count_if(F.col("kind") == "self").alias("__n"),
        F.array_sort(F.collect_set(F.when(active, name))).alias("__rules"),
        F.array_join(F.array_sort(F.collect_set(F.when(active, F.col("category")))), ",").alias("categories"),
    )
    again = per.withColumn("__k", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__n"))))
    return again.select("page_id", "url", "fetched_at", "host", (F.size("__rules") > 0).alias("blocked"), F.size("__rules").cast("long").alias("n_rules"), "categories", F.get("__rules", F.lit(0)).alias("rule"))


def keep_allowed(captures: DataFrame, entries: DataFrame) -> DataFrame:
    return apply_lists(captures, entries).where("not blocked")


#: The query's dates: pages carry none, so the page id gives the day of the fetch.
FETCHED = "timestamp_seconds(1704067200 + 86400 * pmod(coalesce(page_id, 0), 366))"
#: The query's list, by rule: (kind, share: one key in so many, day added, day removed, day added again, categories).
LIST = (("domain", 5, 20, 150, 260, ("spam", "adult", "malware")), ("prefix", 7, 60, 200, 330, ("thin", "spam", "mirror")), ("param", 2, 90, 240, 300, ("tracking",)))


def rule_list(pages: DataFrame) -> DataFrame:
    """A dated list over the keys that the pages have: the checksum of a key says whether and when it is listed."""
    keys = capture_keys(pages.select("page_id", "url")).select("rule.kind", "rule.key").where("kind <> 'self'").distinct()
    crc = draw("list", F.col("key"))
    day = lambda d: F.timestamp_seconds(F.lit(1704067200) + 86400 * (F.lit(d) + F.shiftright(crc, 6) % 30))
    out = None
    for kind, share, on, off, again, categories in LIST:
        # whole top-level and second-level domains aren't listed: they'd take in most hosts
        listed = keys.where((F.col("kind") == kind) & (crc % share == 0) & ((F.col("kind") != "domain") | (F.size(F.split("key", "\\.")) > 2)))
        category = F.element_at(F.array(*map(F.lit, categories)), (F.shiftright(crc, 3) % len(categories) + 1).cast("int"))
        events = F.explode(F.array(*(F.struct(F.lit(a).alias("action"), day(d).alias("at")) for a, d in (("add", on), ("remove", off), ("add", again)))))
        rows = listed.select("kind", "key", category.alias("category"), events.alias("e")).select("kind", "key", "e.action", "e.at", "category")
        out = rows if out is None else out.unionByName(rows)
    return out


def oracle_sql() -> str:
    """The query's result as DuckDB SQL over the table pages."""
    rules = []
    for kind, share, on, off, again, categories in LIST:
        names = "[" + ", ".join(f"'{c}'" for c in categories) + "]"
        for action, d in (("add", on), ("remove", off), ("add", again)):
            wide = " AND len(string_split(key, '.')) > 2" if kind == "domain" else ""
            rules.append(f"SELECT kind, key, '{action}' AS action, 1704067200 + 86400 * ({d} + (crc >> 6) % 30) AS moment, {names}[((crc >> 3) % {len(categories)}) + 1] AS category FROM drawn WHERE kind = '{kind}' AND crc % {share} = 0{wide}")
    return rf"""
WITH part AS (SELECT page_id, url, 1704067200 + 86400 * (page_id % 366) AS fetched,
        rtrim(lower(regexp_replace(regexp_replace(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1), '^.*@', ''), ':[0-9]*$', '')), '.') AS host,
        list_filter(string_split(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)', 1), '/'), lambda x: x <> '') AS steps,
        list_distinct(list_filter(list_transform(string_split(regexp_extract(url, '^[^?#]*\?([^#]*)', 1), '&'), lambda x: lower(string_split(x, '=')[1])), lambda x: x <> '')) AS params FROM pages),
cand AS (SELECT page_id, 'domain' AS kind, unnest([array_to_string(string_split(host, '.')[i:], '.') for i in range(1, len(string_split(host, '.')) + 1)]) AS key FROM part WHERE host <> ''
        UNION ALL SELECT page_id, 'prefix', unnest([host || '/' || array_to_string(steps[:i], '/') for i in range(1, len(steps) + 1)]) FROM part WHERE host <> ''
        UNION ALL SELECT page_id, 'param', unnest(params) FROM part WHERE host <> ''),
drawn AS (SELECT DISTINCT kind, key, ('0x' || substr(md5('list|' || key), 1, 15))::BIGINT AS crc FROM cand),
entry AS ({" UNION ALL ".join(rules)}),
span AS (SELECT *, lead(moment) OVER (PARTITION BY kind, key ORDER BY moment) AS until FROM entry),
hit AS (SELECT c.page_id, c.kind || ':' || c.key AS rule, s.category FROM cand c JOIN part p USING (page_id) JOIN span s ON c.kind = s.kind AND c.key = s.key
        WHERE s.action = 'add' AND s.moment <= p.fetched AND (s.until IS NULL OR p.fetched < s.until)),
per AS (SELECT page_id, count(DISTINCT rule) AS n, min(rule) AS rule, string_agg(DISTINCT category, ',' ORDER BY category) AS categories FROM hit GROUP BY page_id)
SELECT page_id, url, fetched::BIGINT AS fetched_s, host, coalesce(n, 0) > 0 AS blocked, coalesce(n, 0)::BIGINT AS n_rules, coalesce(categories, '') AS categories, rule
FROM part LEFT JOIN per USING (page_id)"""
