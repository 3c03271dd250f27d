from pyspark.sql import functions as F

from shiftscan.llm import urls
from shiftscan.llm.queries import URL_RULES


def judged(spark, rows, listed, **o):
    pages = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit("clash"))
    return {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages, spark.createDataFrame([(x,) for x in listed], "url string"), URL_RULES, **o).collect()}


def test_rules_and_list(spark):
    rows = [
        (1, "http://A.Example.COM/en/1?x#y"), (2, "https://www.example.com/en/"), (3, "http://x.net/es/1"), (4, "http://x.net/fr"), (5, "http://listed.org/p/?a"), (6, "http://free.org/p"), (7, None), (8, "no scheme"),
        (9, "http://notcom/"), (10, "http://com"), (11, "http://WWW.listed.org/p/index.html"), (12, "x://h?a/b"), (13, ""), (14, "http://é.org/ü"),
    ]
    got = judged(spark, rows, ["listed.org/p", "listed.org/p", None, "other.org"])
    assert got[1] == ("a.example.com", "/en/1", "example.com/en/", "block")
    assert got[2] == ("www.example.com", "/en/", "www.example.com/en/", "allow")
    assert got[3][2:] == ("net/es/", "block") and got[4][2:] == (None, "allow")
    assert got[5][2:] == got[11][2:] == (None, "block") and got[6][2:] == (None, "allow")
    assert got[7] == got[8] == got[13] == ("", "", None, "allow")
    assert got[9][2] is None and got[10][1:3] == ("", None) and got[12][:2] == ("h", "") and got[14][:2] == ("é.org", "/ü")


def test_full_filter_only_costs_time(spark):
    listed = [f"h{i}.org/p" for i in range(500)]
    rows = [(i, f"http://h{i}.org/p/") for i in range(0, 1000, 7)]
    want = {i: "block" if i < 500 else "allow" for i, _ in rows}
    for blocks in (1, 1 << 15):
        assert {k: v[3] for k, v in judged(spark, rows, listed, max_blocks=blocks).items()} == want
    assert judged(spark, [], listed) == {} and judged(spark, rows[:2], [])[0][3] == "allow"


def test_clashing_columns(spark):
    names = ["w0", "w7", "block", "key", "at", "maybe", "sure", "row", "_at", "_key", "_block", "a.b"]
    pages = spark.createDataFrame([(1, "http://listed.org/p", *range(12)), (2, "http://x.net/es/1", *range(12))], ["page_id", "url", *names])
    got = urls.judge(pages, spark.createDataFrame([("listed.org/p",)], "url string"), URL_RULES)
    assert got.columns == [*pages.columns, "host", "path", "rule", "verdict", "listed"]
    assert [tuple(r)[2:14] + (r.verdict,) for r in got.orderBy("page_id").collect()] == [(*range(12), "block")] * 2
