"""URL filters: explicit rules, and host reputation by empirical Bayes.

Rules name a host and a start of the path; the longest that fits decides. Other
pages are judged by their host's reputation. Labelled page outcomes are counted
by host, registered domain and suffix (each with partial counts before the
shuffle). A host's rate of bad pages gets a beta prior around its domain's rate,
that one a prior around its suffix's and this one around the rate of all pages;
how strongly each level shrinks comes from the spread of its counts beyond
binomial noise (method of moments for the beta-binomial). A host is blocked if
the lower posterior bound of its rate is above a limit: few outcomes do not
suffice for that.

Defined cases: a null url, or one without ``://``, has empty host and path and is
judged by the reputation of the empty host; outcomes that are null do not count;
without any outcome nobody is blocked; repeated rows are judged alike and count
each; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import ascii_lower, cut, read_table

LIMIT = 0.3
CREDIBLE = 0.95
#: Suffixes of two labels under which names are registered.
LONG_SUFFIXES = ("ac.uk", "co.in", "co.jp", "co.kr", "co.nz", "co.uk", "co.za", "com.ar", "com.au", "com.br", "com.cn", "com.mx", "com.tr", "com.tw", "gov.uk", "ne.jp", "or.jp", "org.au", "org.uk")
#: Least and greatest correlation of two outcomes of a unit: strengths 9999 and 1.
SPREAD = (1e-4, 0.5)


def host_of(url: Column) -> Column:
    return ascii_lower(F.regexp_extract(after_scheme(url), "^[^/?#]*", 0))


def path_of(url: Column) -> Column:
    return F.regexp_extract(after_scheme(url), "^[^/?#]*([^?#]*)", 1)


def after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(F.coalesce(at, F.lit(0)) == 0, F.lit("")).otherwise(F.substring(url, at + 3, F.length(url)))


def suffix_of(host: Column) -> Column:
    long = F.substring_index(host, ".", -2)
    return F.when(long.isin(*LONG_SUFFIXES), long).otherwise(F.substring_index(host, ".", -1))


def domain_of(host: Column) -> Column:
    """The registered domain: the suffix and one label more."""
    long = F.substring_index(host, ".", -2)
    return F.when(long.isin(*LONG_SUFFIXES), F.substring_index(host, ".", -3)).otherwise(long)


def rule_column(host: Column, path: Column, rules: Sequence[tuple[str, str]]) -> Column:
    """Struct ``(rule, action)`` of the longest fitting rule, or null.

    A rule is (action, pattern); rules are a parameter, and few, so they are part
    of the plan.
    """
    found = F.lit(None).cast("struct<rule: string, action: string>")
    for action, pattern in sorted(rules, key=lambda r: len(r[1])):
        own_host, slash, start = pattern.partition("/")
        fits = ((host == own_host) | F.endswith(host, F.lit("." + own_host))) & F.startswith(path, F.lit(slash + start))
        found = F.when(fits, F.struct(F.lit(pattern).alias("rule"), F.lit(action).alias("action"))).otherwise(found)
    return found


def beta_tail(a: np.ndarray, b: np.ndarray, x: float) -> np.ndarray:
    """P(X > x) for beta(a, b), by the continued fraction of the incomplete beta."""
    lbeta = np.array([math.lgamma(p) + math.lgamma(q) - math.lgamma(p + q) for p, q in zip(a, b)])
    front = np.exp(a * math.log(x) + b * math.log1p(-x) - lbeta)
    swap = x > (a + 1) / (a + b + 2)
    p, q, z = np.where(swap, b, a), np.where(swap, a, b), np.where(swap, 1 - x, x)
    tiny = 1e-300
    c, d = np.ones_like(p), 1 - (p + q) * z / (p + 1)
    d = 1 / np.where(np.abs(d) < tiny, tiny, d)
    value = d.copy()
    for m in range(1, 400):
        for term in (m * (q - m) * z / ((p + 2 * m - 1) * (p + 2 * m)), -(p + m) * (p + q + m) * z / ((p + 2 * m) * (p + 2 * m + 1))):
            d = 1 + term * d
            d = 1 / np.where(np.abs(d) < tiny, tiny, d)
            c = 1 + term / c
            c = np.where(np.abs(c) < tiny, tiny, c)
            value = value * d * c
        if np.all(np.abs(d * c - 1) < 1e-13):
            break
    below = front * value / p
    return np.clip(np.where(swap, below, 1 - below), 0, 1)


def page_outcomes(pages: DataFrame, url: str, html: str) -> DataFrame:
    """``(host, bad)``: a page is bad if runs of symbols follow a tenth of its words.

    Weak labels that every page can be given, from what it says alone and not from its
    address; better ones take their place.
    """
    runs = F.regexp_count(F.col(f"`{html}`"), F.lit(r"[#*$%]{3}|(&amp;){3}|!!"))
    spaces = F.length(F.col(f"`{html}`")) - F.length(F.replace(F.col(f"`{html}`"), F.lit(" "), F.lit("")))
    return pages.select(host_of(F.col(f"`{url}`")).alias("host"), (10 * runs > spaces + 1).cast("int").alias("bad"))


def strength(counts: DataFrame, mean: str) -> float:
    """Prior strength of a level, from its units' counts ``n``, ``k`` around ``mean``."""
    m = F.col(mean)
    extra = F.sum((F.col("k") - F.col("n") * m) ** 2 - F.col("n") * m * (1 - m))
    most = F.sum(F.col("n") * (F.col("n") - 1) * m * (1 - m))
    found = counts.agg(extra.alias("extra"), most.alias("most")).first()
    share = found.extra / found.most if found.most else SPREAD[1]
    return 1 / min(max(share, SPREAD[0]), SPREAD[1]) - 1


def with_prior(units: DataFrame, above: DataFrame, on: str) -> DataFrame:
    """Units ``(.., n, k)`` with prior mean ``m`` and strength ``e``.

    The mean is the rate of the unit above, its prior included and the unit's own
    outcomes left out. The strength is what the level's spread allows, and no more
    than the evidence behind that mean: their variances add up.
    """
    above = above.select(on, F.col("n").alias("n_above"), F.col("k").alias("k_above"), F.col("m").alias("m_above"), F.col("e").alias("e_above"))
    known = F.col("n_above") - F.col("n") + F.col("e_above")
    joined = units.join(above, on).withColumn("m", (F.col("k_above") - F.col("k") + F.col("m_above") * F.col("e_above")) / known)
    return joined.withColumn("e", 1 / (F.lit(1 / strength(joined, "m")) + 1 / known)).select(*units.columns, "m", "e")


def reputations(outcomes: DataFrame) -> DataFrame:
    """``(host, n, k, a, b)``: outcomes and posterior beta parameters of hosts.

    Every level's counts are smaller than the one below; the three strengths are
    single numbers. The rate of all pages has a uniform prior.
    """
    hosts = cut(outcomes.where("bad is not null").groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum("bad").alias("k")))
    hosts = hosts.select("host", domain_of(F.col("host")).alias("domain"), suffix_of(F.col("host")).alias("suffix"), F.lit("").alias("all"), "n", "k")
    total = [F.sum("n").alias("n"), F.sum("k").alias("k")]
    domains = hosts.groupBy("domain", "suffix", "all").agg(*total)
    suffixes = domains.groupBy("suffix", "all").agg(*total)
    whole = suffixes.groupBy("all").agg(*total).select("all", "n", "k", F.lit(0.5).alias("m"), F.lit(2.0).alias("e"))
    suffixes = with_prior(suffixes, whole, "all")
    domains = with_prior(domains, suffixes, "suffix")
    hosts = with_prior(hosts, domains, "domain")
    return hosts.select("host", "n", "k", (F.col("k") + F.col("m") * F.col("e")).alias("a"), (F.col("n") - F.col("k") + (1 - F.col("m")) * F.col("e")).alias("b"))


def blocked_hosts(reputation: DataFrame, limit: float = LIMIT, credible: float = CREDIBLE) -> DataFrame:
    @F.pandas_udf("double")
    def tail(a: pd.Series, b: pd.Series) -> pd.Series:
        least = 1e-9  # a rate of exactly 0 or 1 everywhere leaves a parameter at 0
        return pd.Series(beta_tail(np.maximum(a.to_numpy(), least), np.maximum(b.to_numpy(), least), limit))

    return reputation.withColumn("p_above", tail("a", "b")).withColumn("blocked", F.col("p_above") >= credible)


def judge_urls(pages: DataFrame, key: str, url: str, rules: Sequence[tuple[str, str]], outcomes: DataFrame) -> DataFrame:
    """``(key, host, path, rule, verdict, p_above)`` of every page."""
    hosts = cut(blocked_hosts(reputations(outcomes)).select("host", "p_above", "blocked"))
    parsed = pages.select(F.col(f"`{key}`").alias("key"), host_of(F.col(f"`{url}`")).alias("host"), path_of(F.col(f"`{url}`")).alias("path"))
    ruled = parsed.withColumn("r", rule_column(F.col("host"), F.col("path"), rules))
    verdict = F.coalesce("r.action", F.when(F.col("blocked"), F.lit("block")).otherwise(F.lit("allow")))
    return ruled.join(hosts, "host", "left").select("key", "host", "path", F.col("r.rule").alias("rule"), verdict.alias("verdict"), F.coalesce("p_above", F.lit(0.0)).alias("p_above"))


#: The rules of the query.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))


def op2_urlfilter(spark, sf_dir):
    """Every page's url under the rules and under the reputation of its host."""
    pages = read_table(spark, sf_dir, "pages")
    judged = judge_urls(pages, "page_id", "url", RULES, page_outcomes(pages, "url", "html"))
    return judged.select(F.col("key").alias("page_id"), "host", "path", "rule", "verdict")


OP2_SQL = r"""
WITH parts AS (
  SELECT page_id, html, CASE WHEN instr(coalesce(url, ''), '://') = 0 THEN '' ELSE substr(url, instr(url, '://') + 3) END AS rest FROM pages
), parsed AS (
  SELECT page_id, html, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts
), outcomes AS (
  SELECT host, CAST(10 * len(regexp_extract_all(html, '[#*$%]{3}|(?:&amp;){3}|!!')) > length(html) - length(replace(html, ' ', '')) + 1 AS INT) AS bad FROM parsed
), labels_of AS (
  SELECT host, list_reverse(string_split(host, '.')) AS l, count(*) AS n, sum(bad) AS k FROM outcomes WHERE bad IS NOT NULL GROUP BY host
), hosts AS (
  SELECT host, n, k, array_to_string(list_reverse(l[1 : long + 2]), '.') AS domain, array_to_string(list_reverse(l[1 : long + 1]), '.') AS suffix
  FROM (SELECT *, CAST(coalesce(l[2] || '.' || l[1] IN (LONG_SUFFIXES), false) AS INT) AS long FROM labels_of)
), domains AS (
  SELECT domain, suffix, sum(n) AS n, sum(k) AS k FROM hosts GROUP BY ALL
), suffixes AS (
  SELECT suffix, sum(n) AS n, sum(k) AS k FROM domains GROUP BY suffix
), whole AS (
  SELECT sum(n) AS n, sum(k) AS k FROM suffixes
), x1 AS (
  SELECT suffix, x.n, x.k, (w.k - x.k + 1.0) / (w.n - x.n + 2.0) AS m, w.n - x.n + 2.0 AS known FROM suffixes x CROSS JOIN whole w
), s1 AS (
  SELECT 1 / least(greatest(sum((k - n * m) ** 2 - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 0.0001), 0.5) - 1 AS s FROM x1
), x AS (
  SELECT *, 1 / (1 / s + 1 / known) AS e FROM x1 CROSS JOIN s1
), d1 AS (
  SELECT d.domain, d.n, d.k, (x.k - d.k + x.m * x.e) / (x.n - d.n + x.e) AS m, x.n - d.n + x.e AS known FROM domains d JOIN x USING (suffix)
), s2 AS (
  SELECT 1 / least(greatest(sum((k - n * m) ** 2 - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 0.0001), 0.5) - 1 AS s FROM d1
), d AS (
  SELECT *, 1 / (1 / s + 1 / known) AS e FROM d1 CROSS JOIN s2
), h1 AS (
  SELECT h.host, h.n, h.k, (d.k - h.k + d.m * d.e) / (d.n - h.n + d.e) AS m, d.n - h.n + d.e AS known FROM hosts h JOIN d USING (domain)
), s3 AS (
  SELECT 1 / least(greatest(sum((k - n * m) ** 2 - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 0.0001), 0.5) - 1 AS s FROM h1
), posterior AS (
  SELECT host, k + m / (1 / s + 1 / known) AS a, n - k + (1 - m) / (1 / s + 1 / known) AS b FROM h1 CROSS JOIN s3
), tails AS (
  SELECT host, list_sum(list_transform(range(20000), lambda i: exp((a - 1) * ln(0.3 + 0.7 * (i + 0.5) / 20000) + (b - 1) * ln(0.7 - 0.7 * (i + 0.5) / 20000) + lgamma(a + b) - lgamma(a) - lgamma(b)))) * 0.7 / 20000 AS p_above FROM posterior
), ruled AS (
  SELECT *, CASE WHEN (host = 'example.org' OR host LIKE '%.example.org') AND path LIKE '/en/1%' THEN 'example.org/en/1'
                 WHEN (host = 'example.org' OR host LIKE '%.example.org') AND path LIKE '/es/%' THEN 'example.org/es/'
                 WHEN (host = 'com' OR host LIKE '%.com') AND path LIKE '/fr/%' THEN 'com/fr/'
                 WHEN (host = 'com' OR host LIKE '%.com') AND path LIKE '/de/%' THEN 'com/de/'
                 WHEN (host = 'org' OR host LIKE '%.org') AND path LIKE '/%' THEN 'org/' END AS rule FROM parsed
)
SELECT page_id, host, path, rule,
       CASE WHEN rule IN ('org/', 'com/fr/') THEN 'allow' WHEN rule IS NOT NULL OR coalesce(p_above, 0) >= 0.95 THEN 'block' ELSE 'allow' END AS verdict
FROM ruled LEFT JOIN tails USING (host)
""".replace("LONG_SUFFIXES", ", ".join(f"'{s}'" for s in LONG_SUFFIXES))
