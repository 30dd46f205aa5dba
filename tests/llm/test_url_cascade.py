import duckdb
import pytest

from metricblock.llm.url_cascade import ALLOW, BLOCK, OP8_SQL, build_cascade, judge_urls, op8_url_cascade, shape_of

URLS = [
    None, "", "no scheme", "http://", "http://net", "http://net/", "HTTP://A.Example.NET/en/x?y", "http://example.net/EN/", "http://example.net?/en/", "http://xexample.net/en/",
    "https://b.example.com/de/", "https://example.com/de", "http://org/fr/1", "http://a.b.org/fr/#x", "http://borg/fr/", "http://a..net/", "http://ÄÖ.net/é", "x://y.net/a://b", "http://net:80/",
]


def plain(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    cut = lambda s, stops: s[: min([s.find(c) for c in stops if c in s] or [len(s)])]
    host = cut(rest, "/?#")
    path = cut(rest[len(host) :], "?#")
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(h + p, v) for rules, v in ((BLOCK, "block"), (ALLOW, "allow")) for h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    rule, verdict = max(fits, key=lambda x: len(x[0]), default=(None, "allow"))
    return host, path, rule, verdict


def test_urls(spark):
    df = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate(URLS)], "page_id long, url string, host string, rule string")
    rows = {r["page_id"]: r for r in judge_urls(df, BLOCK, ALLOW).collect()}
    assert {i: (r["host"], r["path"], r["rule"], r["verdict"]) for i, r in rows.items()} == {i: plain(u) for i, u in enumerate(URLS)}


def test_query_against_sql(spark, sf):
    got = sorted(map(tuple, op8_url_cascade(spark, sf).collect()))
    duckdb.sql(f"CREATE OR REPLACE VIEW pages AS SELECT * FROM '{sf}/pages.parquet'")
    assert got == sorted(duckdb.sql(OP8_SQL).fetchall())


def test_cascade_is_exact_over_its_universe(spark):
    listed = [f"bad{i}.org/" for i in range(300)]
    universe = spark.range(20_000).selectExpr("concat('site', id, '.com/') as key").unionByName(spark.createDataFrame([(k,) for k in listed[::3]], "key string"))
    cascade = build_cascade(universe, listed)
    assert len(cascade.levels) > 2
    held = {r["key"] for r in universe.where(cascade.holds(universe["key"])).collect()}
    assert held == set(listed[::3])
    ours = spark.createDataFrame([(k,) for k in listed], "key string")
    assert ours.where(cascade.holds(ours["key"])).count() == 300


def test_empty_lists_and_tables(spark):
    none = spark.createDataFrame([], "page_id long, url string")
    assert judge_urls(none, BLOCK, ALLOW).count() == 0
    one = spark.createDataFrame([(1, "http://a.net/")], "page_id long, url string")
    assert judge_urls(one, [], []).first()["verdict"] == "allow"
    assert build_cascade(one.selectExpr("url as key"), []).levels == ()
    with pytest.raises(ValueError):
        judge_urls(one, [("a", "/")], [("a", "/")])
    with pytest.raises(ValueError):
        shape_of(10**9, 0.01)


def test_no_join_and_no_exchange_in_the_verdict(spark, sf):
    plan = op8_url_cascade(spark, sf)._jdf.queryExecution().toString()
    assert "Join" not in plan and "Exchange" not in plan and "Python" not in plan
