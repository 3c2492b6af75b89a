from itertools import combinations

from pyspark.sql import functions as F

from manifold_engine.llm import urlrules as U

LISTED = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]


def _listed(spark, urls):
    d = spark.createDataFrame([(u,) for u in urls], "url string")
    d = d.select("url", U.host_of(F.col("url")).alias("h"), U.path_of(F.col("url")).alias("p"))
    return {r.url: (r.h, r.p, r.r.rule if r.r else None, r.r.verdict if r.r else None) for r in d.select("*", U.listed_verdict(F.col("h"), F.col("p"), LISTED).alias("r")).collect()}


def test_parts_and_longest_rule(spark):
    got = _listed(spark, ["HTTP://A.Example.COM/en/71?x", "x://example.net/de/8#f", "x://example.net/de/1", "x://notexample.com/en/7", "x://com/en/", "x://com/en", "nothing", None, "", "a://b://c/d", "x://h\n/p\n/q?z", "x://org?/es/", "x://.org/es/", "x://Éx.org/es/1"])
    assert got["HTTP://A.Example.COM/en/71?x"] == ("a.example.com", "/en/71", "example.com/en/7", "allow")
    assert got["x://example.net/de/8#f"][2:] == ("example.net/de/8", "block")
    assert got["x://example.net/de/1"][2:] == ("net/de/", "allow")
    assert got["x://notexample.com/en/7"][2:] == ("com/en/", "block")
    assert got["x://com/en/"][2:] == ("com/en/", "block") and got["x://com/en"][2] is None
    assert got["nothing"] == got[""] == got[None] == ("", "", None, None)
    assert got["a://b://c/d"][:2] == ("b:", "//c/d")
    assert got["x://h\n/p\n/q?z"][:2] == ("h\n", "/p\n/q")
    assert got["x://org?/es/"][:3] == ("org", "", None)
    assert got["x://.org/es/"][2] == "org/es/" and got["x://Éx.org/es/1"][0] == "Éx.org"


def test_rules_match_brute_force(spark):
    urls = [(f"http://{'spam' if i % 3 == 0 else 'ok'}.site{i % 4}.com/{'win' if i % 2 == 0 else 'read'}/{i}", i % 6 == 0 or i % 17 == 0) for i in range(240)]
    d = spark.createDataFrame(urls, "url string, bad boolean")
    rules = {tuple(r.tokens): (round(r.confidence, 6), round(r.support, 6)) for r in U.mine_rules(d, min_support=0.05, min_confidence=0.8, min_count=1, min_lift=0.0, held_out=False).collect()}
    sets = [(set(r.t), r.bad) for r in d.select(U.tokens_of(F.col("url")).alias("t"), "bad").collect()]
    tokens = sorted({t for s, _ in sets for t in s if sum(t in x for x, _ in sets) >= 12})
    every = {}
    for k in (1, 2, 3, 4, 5):
        for c in combinations(tokens, k):
            n = sum(set(c) <= s for s, _ in sets)
            b = sum(set(c) <= s and bad for s, bad in sets)
            if b >= 0.05 * 240 and b / n >= 0.8:
                every[c] = (round(b / n, 6), round(b / 240, 6))
    want = {c: v for c, v in every.items() if not any(set(o) < set(c) and every[o][0] >= v[0] for o in every)}
    assert rules == want and want
    out = U.judge(d.drop("bad"), [], U.mine_rules(d, min_support=0.05, min_confidence=0.8, min_count=1, min_lift=0.0, held_out=False))
    blocked = {r.url for r in out.where("verdict = 'block'").collect()}
    fit = {u for (u, _), (s, _) in zip(urls, sets) if any(set(c) <= s for c in want)}
    assert blocked == fit


def test_empty_and_clash(spark):
    none = spark.createDataFrame([], "url string, bad boolean")
    rules = U.mine_rules(none)
    d = spark.createDataFrame([(1, None, "z"), (2, "http://a.org/es/", "y"), (2, "http://a.org/es/", "y")], "page_id long, url string, host string")
    out = U.judge(d, LISTED, rules).orderBy("page_id").collect()
    assert [(r.host, r.rule, r.verdict) for r in out] == [("", None, "allow"), ("a.org", "org/es/", "block"), ("a.org", "org/es/", "block")]
    assert U.judge(d.limit(0), LISTED, rules).count() == 0


def _tables(spark, tmp_path, pages, labels):
    spark.createDataFrame(pages, "page_id long, url string, html string").write.mode("overwrite").parquet(str(tmp_path / "pages.parquet"))
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.mode("overwrite").parquet(str(tmp_path / "labels.parquet"))
    return str(tmp_path)


def test_query_finds_planted_rules_and_no_others(spark, tmp_path):
    """Bad pages stand under one host and word together; rules hold on the half that did not mine them."""
    import random

    from manifold_engine.llm.queries import QUERIES

    rng = random.Random(0)
    pages, labels = [], []
    for i in range(1500):
        host, word = rng.choice(("spam", "news", "shop")), rng.choice(("win", "read", "buy"))
        pages.append((i, f"http://{host}.site.org/{word}/{i}", None))
        bad = rng.random() < (0.95 if (host, word) == ("spam", "win") else 0.1)
        if i % 5:
            labels.append((i, int(not bad), 0))
    pages += [(9001, "http://a.example.com/en/7", None), (9002, None, None), (9003, "http://org/es/x", None), (9003, "http://org/es/x", None)]
    out = QUERIES["op1_url_filter"](spark, _tables(spark, tmp_path, pages, labels)).collect()
    assert len(out) == len(pages)
    for r in out:
        planted = r.host == "spam.site.org" and r.path.startswith("/win/")
        if r.page_id < 9000:
            assert (r.verdict == "block") == planted and (r.learnt_rule == "h:spam p:win") == planted, r
    got = {r.page_id: (r.rule, r.verdict) for r in out if r.page_id > 9000}
    assert got == {9001: ("example.com/en/7", "allow"), 9002: (None, "allow"), 9003: ("org/es/", "block")}


def test_labels_without_a_pattern_give_no_rules(spark, sf01):
    """On the given tables labels and urls are independent; host, path, rule and listed verdict are held against SQL."""
    import duckdb

    from manifold_engine.llm.queries import QUERIES

    got = sorted((r.page_id, r.host, r.path, r.rule, r.verdict) for r in QUERIES["op1_url_filter"](spark, sf01).collect())
    rules = " union all ".join(f"select '{v}' as v, '{h}' as h, '{p}' as p" for v, h, p in LISTED)
    sql = f"""with u as (select page_id, coalesce(lower(regexp_extract(url, '^.*?://([^/?#]*)', 1)), '') as host, coalesce(regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1), '') as path from read_parquet('{sf01}/pages.parquet')),
    r as ({rules}), f as (select page_id, arg_max(h || p, length(h || p)) as rule, arg_max(v, length(h || p)) as v from u, r where (host = h or ends_with(host, '.' || h)) and starts_with(path, p) group by page_id)
    select u.page_id, host, path, rule, coalesce(v, 'allow') from u left join f on u.page_id = f.page_id"""
    assert got == sorted(duckdb.sql(sql).fetchall(), key=lambda r: (r[0], r[1], r[2]))
