import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefpat.llm import urlfilter


def test_parts_of_urls(spark):
    cases = {
        "http://A.Example.COM/x/y?q#f": ("a.example.com", "/x/y"), "https://h?x": ("h", ""), "https://h#x": ("h", ""), "ftp://h:80/": ("h:80", "/"),
        "no scheme": ("", ""), "": ("", ""), "://": ("", ""), "a://b://c/d": ("b:", "//c/d"), "x://ÄB/É": ("Äb", "/É"), "http://h/a\nb": ("h", "/a\nb"),
    }
    df = spark.createDataFrame([(u,) for u in [*cases, None]], "url string")
    got = {r.url: (r.host, r.path) for r in df.select("url", urlfilter.host_of(F.col("url")).alias("host"), urlfilter.path_of(F.col("url")).alias("path")).collect()}
    assert got == {**cases, None: ("", "")}


def test_longest_rule_wins(spark):
    cases = [("example.org", "/es/1", "example.org/es/"), ("a.example.org", "/en/19", "example.org/en/1"), ("example.org", "/en/2", "org/"), ("notexample.org", "/es/1", "org/"), ("org", "/", "org/"), ("x.org", "", None), ("a.com", "/fr/", "com/fr/"), ("a.com", "/de/x", "com/de/"), ("acom", "/de/x", None), ("a.net", "/de/", None)]
    df = spark.createDataFrame(cases, "host string, path string, want string")
    for r in df.withColumn("r", urlfilter.rule_column(F.col("host"), F.col("path"), urlfilter.RULES)).collect():
        assert (r.r.rule if r.r else None) == r.want


def test_domains(spark):
    df = spark.createDataFrame([("a.b.example.com",), ("x.y.co.uk",), ("com",), ("",), ("b.c",)], "h string")
    got = {r.h: (r.d, r.s) for r in df.select("h", urlfilter.domain_of(F.col("h")).alias("d"), urlfilter.suffix_of(F.col("h")).alias("s")).collect()}
    assert got == {"a.b.example.com": ("example.com", "com"), "x.y.co.uk": ("y.co.uk", "co.uk"), "com": ("com", "com"), "": ("", ""), "b.c": ("b.c", "c")}


def test_beta_tail():
    for a, b in [(1, 1), (0.5, 3), (2, 7), (40, 60), (3000, 7000), (1e-9, 5), (20, 2)]:
        x = (np.arange(400_000) + 0.5) / 400_000
        density = np.exp((a - 1) * np.log(x) + (b - 1) * np.log1p(-x) - math.lgamma(a) - math.lgamma(b) + math.lgamma(a + b))
        assert urlfilter.beta_tail(np.array([float(a)]), np.array([float(b)]), 0.3)[0] == pytest.approx(density[x > 0.3].sum() / 400_000, abs=2e-3)


def test_reputation_shrinks_and_blocks(spark):
    rows = [("good.one.com", 0)] * 400 + [("bad.two.com", 1)] * 300 + [("fresh.two.com", 1), ("new.three.net", 1)] + [("mixed.four.net", i % 5 == 0) for i in range(300)] + [("null.five.net", None)]
    df = spark.createDataFrame([(h, None if b is None else int(b)) for h, b in rows], "host string, bad int")
    found = {r.host: r for r in urlfilter.blocked_hosts(urlfilter.reputations(df)).collect()}
    assert {h for h, r in found.items() if r.blocked} >= {"bad.two.com"}
    assert not found["good.one.com"].blocked and not found["mixed.four.net"].blocked and not found["new.three.net"].blocked
    mean = lambda h: found[h].a / (found[h].a + found[h].b)
    assert mean("new.three.net") < mean("fresh.two.com")  # one outcome each, but in other company
    assert "null.five.net" not in found


def test_odd_rows(spark):
    pages = spark.createDataFrame([(None, None, None, "c"), (1, "http://x.net/", None, "c"), (1, "http://x.net/", "a b", "c"), (2, "", "z" * 100000, "c")], "page_id long, url string, html string, host string")
    out = urlfilter.judge_urls(pages, "page_id", "url", urlfilter.RULES, urlfilter.page_outcomes(pages, "url", "html"))
    assert sorted((str(r.key), r.host, r.verdict) for r in out.collect()) == [("1", "x.net", "allow"), ("1", "x.net", "allow"), ("2", "", "allow"), ("None", "", "allow")]
    none = pages.limit(0)
    assert urlfilter.judge_urls(none, "page_id", "url", urlfilter.RULES, urlfilter.page_outcomes(none, "url", "html")).count() == 0
