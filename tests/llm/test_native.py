"""Operators that SQL expresses, on small tables with nulls, ties, repeats, long texts and clashing columns."""

import duckdb
import pytest
from pyspark.sql import functions as F

from walkrank.llm import licenses, mixing, urlfilter


def in_duckdb(sql, **tables):
    con = duckdb.connect()
    for name, frame in tables.items():
        con.register(name, frame)
    return con.sql(sql).fetchall()


TEXTS = ["", "MIT License", "the mit   license; MIT license", "Apache-License, apache license", "permission is hereby granted, free of charge, to any lucky person obtaining a copy of this software and associated documentation files",
         "GNU General Public License general public license", "mit", "license mit", "É mit license", "x " * 3000 + "mit license", "K mit license"]


def test_licenses(spark):
    import pandas as pd

    rows = [(i, t, 1) for i, t in enumerate(TEXTS)] + [(50, None, 1), (1, "MIT License", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, label int")
    got = sorted(map(tuple, licenses.scan(docs).collect()), key=str)
    assert len(got) == len(rows)
    frame = pd.DataFrame([(i, t) for i, t, _ in rows[:-1]], columns=["doc_id", "text"])
    want = in_duckdb(licenses.oracle_sql(), documents=frame)
    assert sorted({tuple(x) for x in got}, key=str) == sorted(want, key=str)
    by = {r[0]: r for r in got}
    assert by[2][2:7] == (2, 1, 3, "mit", "mit") and by[5][2] == 2 and by[4][6] == "mit" and by[4][7] > 0.8 and by[8][2] == 0 and by[50][1] == 0
    assert licenses.scan(docs.limit(0)).count() == 0
    assert licenses.scan(docs.withColumn("doc_id", F.lit(None).cast("long"))).count() == len(rows)


def test_license_hash_tables_are_bounded():
    with pytest.raises(ValueError):
        licenses.templates(clauses=(("x", "w " * 100),))


def test_mixing_meets_its_targets(spark):
    rows = [(i, "w " * (1 + i % 7), "hot" if i % 3 else f"s{i % 5}") for i in range(600)] + [(None, None, None), (601, "a b", None), (3, "w w w w", "s3")]
    docs = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, source string, copies int")
    got = mixing.mix(docs, target=0.5, limit=4.0).collect()
    assert len(got) == len(rows) and {r.source for r in got} == {"hot", "s0", "s1", "s2", "s3", "s4", None}
    total = sum(r.n_tokens for r in got)
    for s in {r.source for r in got}:
        own = [r for r in got if r.source == s]
        budget = own[0].weight * total
        spent = sum(r.copies * r.n_tokens for r in own)
        assert budget - 8 <= spent <= budget + 1 and max(r.copies for r in own) - min(r.copies for r in own) <= 1
        assert spent <= 4 * sum(r.n_tokens for r in own)
    again = mixing.mix(docs.repartition(7), target=0.5, limit=4.0).collect()
    assert sorted(map(tuple, again), key=str) == sorted(map(tuple, got), key=str)
    whole = mixing.realise(docs, budget="cover")
    assert whole.columns == docs.columns and whole.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()
    assert mixing.mix(docs.limit(0)).count() == 0
    assert [r.copies for r in mixing.mix(docs.where("text is null")).collect()] == [1]


def test_url_filter(spark):
    day = lambda d: f"2024-01-{d:02d} 00:00:00"
    entries = [("domain", "bad.org", "add", 5, "spam"), ("domain", "bad.org", "remove", 10, None), ("domain", "bad.org", "add", 10, "adult"), ("domain", "bad.org", "remove", 20, None),
               ("prefix", "ok.org/a", "add", 3, "thin"), ("param", "ref", "add", 1, "t"), (None, "x", "add", 1, "t"), ("domain", None, "add", 1, "t"), ("domain", "ok.org", "drop", 1, "t")]
    e = spark.createDataFrame([(k, key, a, day(d), c, 1) for k, key, a, d, c in entries], "kind string, key string, action string, at string, category string, page_id int").withColumn("at", F.to_timestamp("at"))
    urls = [("http://x.BAD.org:80/q", 4), ("http://bad.org", 5), ("https://u@a.bad.org./", 10), ("http://bad.org", 20), ("http://ok.org/a/b", 3), ("http://ok.org/ab", 3), ("http://ok.org/?Ref=1&x", 2), (None, 3), ("nonsense", 3), ("http://bad.org", 5), ("http://bad.org", None)]
    c = spark.createDataFrame([(i if i != 9 else 1, u, None if d is None else day(d), "k") for i, (u, d) in enumerate(urls)], "page_id long, url string, fetched_at string, key string").withColumn("fetched_at", F.to_timestamp("fetched_at"))
    got = urlfilter.apply_lists(c, e).collect()
    assert len(got) == len(urls)
    by = {r.page_id: (r.blocked, r.categories, r.rule) for r in got}
    assert by[0][0] is False and by[1] == (True, "spam", "domain:bad.org") and by[2] == (True, "adult", "domain:bad.org") and by[3][0] is False
    assert by[4] == (True, "thin", "prefix:ok.org/a") and by[5][0] is False and by[6] == (True, "t", "param:ref") and not by[7][0] and not by[8][0] and not by[10][0]
    assert urlfilter.apply_lists(c.limit(0), e).count() == 0 and urlfilter.apply_lists(c, e.limit(0)).where("blocked").count() == 0


def test_url_prefixes_of_any_depth(spark):
    e = spark.createDataFrame([("prefix", "ok.org/a/b/c/d/e", "add", "2024-01-01 00:00:00", "deep")], "kind string, key string, action string, at string, category string").withColumn("at", F.to_timestamp("at"))
    c = spark.createDataFrame([(1, "http://ok.org/a/b/c/d/e/f?x=1"), (2, "http://ok.org/a/b/c/d"), (3, "http://ok.org/a/b/c/d/ef")], "page_id long, url string").withColumn("fetched_at", F.to_timestamp(F.lit("2024-01-02 00:00:00")))
    assert {r.page_id: r.rule for r in urlfilter.apply_lists(c, e).collect()} == {1: "prefix:ok.org/a/b/c/d/e", 2: None, 3: None}
