"""The relational surface around the method: scans, joins, aggregates, windows, set operations, functions."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.functions.session import read
from walkrank.sources import graphs

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}
EVENTS = ["click", "error", "purchase", "signup", "view"]


def case(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f
    return put


@case("scan_parquet", "SELECT o_orderstatus AS status, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders WHERE o_orderdate >= TIMESTAMP '1995-01-01' GROUP BY 1")
def _(spark, d):
    return read(spark, d, "orders").where("o_orderdate >= timestamp'1995-01-01'").groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@case("filter_tokens", r"SELECT lang, count(*) AS n FROM (SELECT lang, unnest(string_split_regex(lower(text), '[^\p{L}]+')) AS w FROM documents WHERE lang IN ('en', 'fr')) WHERE length(w) BETWEEN 3 AND 8 GROUP BY lang")
def _(spark, d):
    w = read(spark, d, "documents").where(F.col("lang").isin("en", "fr")).select("lang", F.explode(F.split(F.lower("text"), "[^\\p{L}]+")).alias("w"))
    return w.where(F.length("w").between(3, 8)).groupBy("lang").agg(F.count("*").alias("n"))


@case("join_rank_edges", "SELECT n_name AS nation, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def _(spark, d):
    o, c, n = (read(spark, d, t) for t in ("orders", "customer", "nation"))
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy(F.col("n_name").alias("nation")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@case("knn_edges", "SELECT vec_id, nearest, sim FROM (SELECT a.vec_id, b.vec_id AS nearest, round(list_inner_product(a.e, b.e), 6) AS sim, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_inner_product(a.e, b.e), 9) DESC, b.vec_id) AS r FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE r = 1")
def _(spark, d):
    e = read(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    return graphs.nearest(e, 1, cosine=False).select(F.col("id").alias("vec_id"), F.col("other").alias("nearest"), F.round("sim", 6).alias("sim"))


@case("interval_activity_edges", "SELECT a.user_id AS src, b.user_id AS dst, count(*) AS n FROM events a JOIN events b ON b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE AND a.user_id <> b.user_id GROUP BY 1, 2")
def _(spark, d):
    e = read(spark, d, "events").select(F.col("user_id").cast("long").alias("user"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    return graphs.following(e.where("user is not null and t is not null"), 300_000_000)


@case("asof_user_order", "SELECT e.event_id, o.o_orderkey AS order_key FROM events e ASOF LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY ALL) o ON e.user_id = o.o_custkey AND e.ts >= o.o_orderdate")
def _(spark, d):
    # union, then the last order seen: one shuffle on the user, no row pairs
    e = read(spark, d, "events").select(F.col("user_id").alias("u"), F.col("ts").cast("timestamp").alias("t"), "event_id", F.lit(None).cast("long").alias("k"), F.lit(1).alias("side"))
    o = read(spark, d, "orders").groupBy(F.col("o_custkey").alias("u"), F.col("o_orderdate").cast("timestamp").alias("t")).agg(F.max("o_orderkey").alias("k"))
    both = e.unionByName(o.withColumn("event_id", F.lit(None).cast("long")).withColumn("side", F.lit(0)))
    seen = W.partitionBy("u").orderBy("t", "side").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn("order_key", F.last("k", ignorenulls=True).over(seen)).where("side = 1").select("event_id", "order_key")


@case("agg_basic", "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(min(value), 6) AS low, round(max(value), 6) AS high, count(DISTINCT user_id) AS users, arg_max(event_id, ts) AS latest, count(*) FILTER (value > 50) AS large FROM events GROUP BY 1")
def _(spark, d):
    return read(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.min("value"), 6).alias("low"), F.round(F.max("value"), 6).alias("high"), F.countDistinct("user_id").alias("users"), F.max_by("event_id", "ts").alias("latest"), F.count_if(F.col("value") > 50).alias("large"))


@case("rollup_trade", "SELECT r_name AS region, n_name AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (1, 2)")
def _(spark, d):
    c, n, r = (read(spark, d, t) for t in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count("*").alias("n"))


@case("cube_runs", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY CUBE (1, 2)")
def _(spark, d):
    return read(spark, d, "orders").cube(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n"))


@case("grouping_sets_events", "SELECT event_type, user_id % 5 AS g, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (g), ())")
def _(spark, d):
    read(spark, d, "events").createOrReplaceTempView("walkrank_events")
    return spark.sql("SELECT event_type, g, count(*) AS n FROM (SELECT event_type, user_id % 5 AS g FROM walkrank_events) GROUP BY GROUPING SETS ((event_type), (g), ())")


@case("pivot_event_types", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in EVENTS) + " FROM events GROUP BY user_id")
def _(spark, d):
    kinds = EVENTS
    return read(spark, d, "events").groupBy("user_id").pivot("event_type", kinds).agg(F.count(F.lit(1))).select("user_id", *(F.coalesce(t, F.lit(0)).alias(t) for t in kinds))


@case("unpivot_part", "SELECT p_partkey, 'size' AS what, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def _(spark, d):
    return read(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "what", "value")


@case("next_user", "SELECT event_id, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS nxt, lag(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS prev FROM events")
def _(spark, d):
    w = W.partitionBy("event_type").orderBy("ts", "event_id")
    return read(spark, d, "events").select("event_id", F.lead("user_id").over(w).alias("nxt"), F.lag("user_id").over(w).alias("prev"))


@case("running_mass", "SELECT c_custkey, round(sum(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey ROWS UNBOUNDED PRECEDING), 2) AS mass, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)::INT AS quarter FROM customer")
def _(spark, d):
    w = W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return read(spark, d, "customer").select("c_custkey", F.round(F.sum("c_acctbal").over(w.rowsBetween(W.unboundedPreceding, 0)), 2).alias("mass"), F.ntile(4).over(w).alias("quarter"))


@case("rank_ties", "SELECT p_partkey, rank() OVER w::INT AS rank, dense_rank() OVER w::INT AS dense, round(percent_rank() OVER w, 9) AS pct FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def _(spark, d):
    w = W.partitionBy("p_brand").orderBy("p_size")
    return read(spark, d, "part").select("p_partkey", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 9).alias("pct"))


@case("range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(spark, d):
    w = W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return read(spark, d, "events").withColumn("s", F.round(F.col("ts").cast("timestamp").cast("double")).cast("long")).select("event_id", F.count("*").over(w).alias("n"))


@case("topk_per_lang", "SELECT lang, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 5")
def _(spark, d):
    w = W.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return read(spark, d, "documents").select("lang", "doc_id", "n_chars", F.row_number().over(w).alias("r")).where("r <= 5").drop("r")


for _name, _op in (("topk_intersect", "INTERSECT"), ("topk_except", "EXCEPT"), ("topk_union", "UNION")):
    @case(_name, f"(SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F') {_op} (SELECT o_custkey FROM orders WHERE o_orderstatus = 'O')")
    def _(spark, d, op=_op):
        o = read(spark, d, "orders")
        a, b = (o.where(F.col("o_orderstatus") == s).select(F.col("o_custkey").alias("k")) for s in "FO")
        return {"INTERSECT": a.intersect(b), "EXCEPT": a.subtract(b), "UNION": a.union(b).distinct()}[op]


@case("semi_anti", "SELECT (SELECT count(*) FROM customer SEMI JOIN orders ON c_custkey = o_custkey) AS active, (SELECT count(*) FROM customer ANTI JOIN orders ON c_custkey = o_custkey) AS idle")
def _(spark, d):
    c, o = read(spark, d, "customer"), read(spark, d, "orders")
    n = lambda how, name: c.join(o, F.col("c_custkey") == F.col("o_custkey"), how).agg(F.count("*").alias(name))
    return n("left_semi", "active").crossJoin(n("left_anti", "idle"))


@case("tokenize", r"SELECT doc_id, len(list_filter(string_split_regex(lower(text), '[^\p{L}]+'), lambda w: length(w) >= 3))::BIGINT AS n FROM documents")
def _(spark, d):
    from walkrank.sources.graphs import tokens
    return read(spark, d, "documents").select("doc_id", F.size(tokens(F.col("text"))).cast("long").alias("n"))


@case("page_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def _(spark, d):
    return read(spark, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host")).agg(F.count("*").alias("n"))


@case("orders_by_month", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, round(avg(date_diff('day', o_orderdate::DATE, DATE '2000-01-01')), 6) AS age FROM orders GROUP BY 1")
def _(spark, d):
    return read(spark, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"), F.round(F.avg(F.datediff(F.lit("2000-01-01").cast("date"), F.to_date("o_orderdate"))), 6).alias("age"))


@case("adjacency_arrays", "SELECT o_custkey AS src, count(DISTINCT l_partkey) AS d, md5(array_to_string(list(DISTINCT l_partkey ORDER BY l_partkey), ',')) AS nbrs FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def _(spark, d):
    j = read(spark, d, "orders").join(read(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy(F.col("o_custkey").alias("src")).agg(F.array_sort(F.collect_set("l_partkey")).alias("a")).select("src", F.size("a").cast("long").alias("d"), F.md5(F.array_join("a", ",").cast("binary")).alias("nbrs"))


@case("params_map", "SELECT c_mktsegment AS segment, n::BIGINT AS n FROM (SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1)")
def _(spark, d):
    m = read(spark, d, "customer").groupBy("c_mktsegment").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m"))
    return m.select(F.explode("m").alias("segment", "n"))


@case("event_props", "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k, count(props->>'$.k') AS n FROM events GROUP BY 1")
def _(spark, d):
    e = read(spark, d, "events").select("event_type", F.from_json("props", "k BIGINT").alias("p"))
    return e.groupBy("event_type").agg(F.sum("p.k").alias("k"), F.count("p.k").alias("n"))


# --- batch twins of the streams ---

@case("tumbling_edges", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1, 2")
def _(spark, d):
    return read(spark, d, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "event_type", "n", "users")


@case("sliding_edges", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY 1")
def _(spark, d):
    return read(spark, d, "events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@case("session_edges", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 30 MINUTE)::INT AS fresh FROM events)) GROUP BY user_id, coalesce(s, 0)")
def _(spark, d):
    return read(spark, d, "events").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


# --- user-defined functions ---

@case("udaf_mass", "SELECT o_orderpriority AS priority, round(sum(o_totalprice), 2) AS mass FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC) AS r FROM orders) WHERE r <= 10 GROUP BY 1")
def _(spark, d):
    @F.pandas_udf("double")
    def top_mass(v: pd.Series) -> float:
        return float(v.nlargest(10).sum())

    return read(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("priority")).agg(F.round(top_mass("o_totalprice"), 2).alias("mass"))


@case("udtf_tokens", r"SELECT item_id, w AS word FROM (SELECT item_id, unnest(string_split_regex(lower(text), '[^\p{L}]+')) AS w FROM benchmark) WHERE length(w) >= 3")
def _(spark, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="word string")
    class Tokens:
        def eval(self, text: str):
            word = ""
            for ch in (text or "").lower() + " ":
                if ch.isalpha():
                    word += ch
                else:
                    if len(word) >= 3:
                        yield (word,)
                    word = ""

    spark.udtf.register("walkrank_tokens", Tokens)
    read(spark, d, "benchmark").createOrReplaceTempView("walkrank_items")
    return spark.sql("SELECT item_id, t.word FROM walkrank_items, LATERAL walkrank_tokens(text) AS t")


@case("sql_parameters", "SELECT o_orderstatus AS status, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY 1")
def _(spark, d):
    return spark.sql("SELECT o_orderstatus AS status, count(*) AS n FROM {orders} WHERE o_totalprice > :least GROUP BY 1", args={"least": 100000}, orders=read(spark, d, "orders"))
