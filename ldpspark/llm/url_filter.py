"""URL filter: explicit host and path rules, then host reputation by empirical Bayes."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import small_batches

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

#: (verdict, host, path prefix)
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
BAD_RATE = 0.35
#: Posterior chance of a bad rate over ``BAD_RATE`` from which a host is blocked.
SURE = 0.95
#: Public suffixes of two labels, under which names are registered. A deployment passes a full list.
SUFFIXES = ("ac.uk", "co.in", "co.jp", "co.nz", "co.uk", "co.za", "com.au", "com.br", "com.cn", "com.mx", "gov.uk", "net.au", "org.au", "org.uk")


def registered(host: Column, suffixes: tuple[str, ...] = SUFFIXES) -> tuple[Column, Column]:
    """Registered domain and public suffix of a host: the label before the suffix and the suffix, which is one of ``suffixes`` or the last label."""
    two = F.substring_index(host, ".", -2)
    long = two.isin(*suffixes) if suffixes else F.lit(False)
    return F.when(long, F.substring_index(host, ".", -3)).otherwise(two), F.when(long, two).otherwise(F.substring_index(host, ".", -1))


def beta_cdf(a: np.ndarray, b: np.ndarray, x: float) -> np.ndarray:
    """Share of a beta distribution at or below ``x``, by the continued fraction of the incomplete beta function."""
    swap = x > (a + 1) / (a + b + 2)  # where the fraction of the other tail converges faster
    a, b, x = np.where(swap, b, a), np.where(swap, a, b), np.where(swap, 1 - x, x)
    c, f = np.ones_like(a), 1 / (1 - (a + b) * x / (a + 1))
    d = f.copy()
    for m in range(1, 400):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d, c = 1 / (1 + term * d), 1 + term / c
            f = f * c * d
    gamma = np.vectorize(math.lgamma, otypes=[float])
    front = np.exp(gamma(a + b) - gamma(a) - gamma(b) + a * np.log(x) + b * np.log1p(-x)) / a if len(a) else a
    return np.where(swap, 1 - front * f, front * f)


def url_parts(url: str = "url") -> tuple[Column, Column]:
    """Host and path as columns; both empty for null or where there is no ``://``."""
    u = F.col(url).cast("string")
    has = F.coalesce(F.instr(u, "://") > 0, F.lit(False))
    rest = F.when(has, F.expr(f"substring(cast({url} as string), instr(cast({url} as string), '://') + 3)")).otherwise("")
    raw = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.translate(raw, UPPER, UPPER.lower()), path


def matched_rule(host: str, path: str, rules: tuple[tuple[str, str, str], ...] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits, as its text and its verdict; null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r[1], r[2])):
        fits = ((F.col(host) == h) | F.col(host).endswith("." + h)) & F.col(path).startswith(p)
        name, verdict = F.when(fits, h + p).otherwise(name), F.when(fits, what).otherwise(verdict)
    return name, verdict


def _strength(level: DataFrame) -> DataFrame:
    """One row: prior strength of a level's bad rates around their mean, by moments of the beta-binomial; the weakest where outcomes are too few to tell."""
    t = level.where("n > 0").agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("N"), F.sum("bad").alias("B"), F.sum(F.col("bad") * F.col("bad") / F.col("n")).alias("Q"), F.sum((F.col("n") * F.col("n")).cast("double")).alias("R"))
    mean = (F.col("B") + 1.0) / (F.col("N") + 2.0)
    between = (F.col("Q") - F.col("B") * F.col("B") / F.col("N")) / (mean * (1 - mean)) - (F.col("k") - 1)
    room = F.col("N") - F.col("R") / F.col("N") - (F.col("k") - 1)
    rho = F.when((F.coalesce(F.col("N"), F.lit(0)) > 0) & (room > 0), between / room).otherwise(0.5)
    rho = F.greatest(F.lit(0.001), F.least(F.lit(0.5), F.coalesce(rho, F.lit(0.5))))
    return t.select((1 / rho - 1).alias("strength"))


def host_reputation(pages: DataFrame, outcomes: DataFrame, suffixes: tuple[str, ...] = SUFFIXES) -> DataFrame:
    """Posterior of each host's bad rate, a beta distribution: ``host``, ``n``, ``bad``, ``mean``, ``weight`` (its parameters are mean x weight and the rest of weight).

    ``pages`` has ``page_id`` and ``url``; ``outcomes`` has ``page_id`` and ``bad`` (0 or 1; null counts as no outcome). Counts are shrunk level by level: a suffix
    toward the overall rate, a registered domain (the label before a public suffix, and the suffix) toward its suffix, a host toward its domain, each with
    the strength that the level's own spread of rates suggests. A host without outcomes takes its domain's rate. An
    outcome without a page is ignored.
    """
    host, _ = url_parts()
    named = pages.select("page_id", host.alias("host"))
    voted = named.join(outcomes.select("page_id", F.col("bad").cast("long").alias("bad")).where("bad is not null"), "page_id", "left")
    hosts = voted.groupBy("host").agg(F.count("bad").alias("n"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad"))
    domain, suffix = registered(F.col("host"), suffixes)
    hosts = hosts.withColumn("domain", domain).withColumn("suffix", suffix)
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    top = suffixes.agg(((F.coalesce(F.sum("bad"), F.lit(0)) + 1.0) / (F.coalesce(F.sum("n"), F.lit(0)) + 2.0)).alias("prior"))
    shrunk = (F.col("bad") + F.col("strength") * F.col("prior")) / (F.col("n") + F.col("strength"))
    s = suffixes.crossJoin(F.broadcast(top)).crossJoin(F.broadcast(_strength(suffixes))).select("suffix", shrunk.alias("prior"))
    d = domains.join(s, "suffix").crossJoin(F.broadcast(_strength(domains))).select("domain", shrunk.alias("prior"))
    h = hosts.join(d, "domain").crossJoin(F.broadcast(_strength(hosts)))
    return h.select("host", "n", "bad", shrunk.alias("mean"), (F.col("n") + F.col("strength")).alias("weight"))


def judged(pages: DataFrame, outcomes: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, bad_rate: float = BAD_RATE, sure: float = SURE, suffixes: tuple[str, ...] = SUFFIXES) -> DataFrame:
    """Verdict for each page: ``page_id``, ``host``, ``path``, ``rule``, ``verdict``, ``bad_chance``.

    The longest rule that fits decides. Else the host is blocked if its bad rate is over ``bad_rate`` with posterior probability ``sure`` (``bad_chance``), which is to say
    that the rate's lower posterior bound of that level is over ``bad_rate``: a host needs evidence to be blocked. A url that is null or has no
    ``://`` has empty host and path, which are judged as a host. Rows that repeat stay; further columns are ignored.
    """
    small_batches(pages.sparkSession)
    host, path = url_parts()

    @F.pandas_udf("double")
    def over(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for mean, weight in parts:
            yield pd.Series(1 - beta_cdf((mean * weight).to_numpy(), ((1 - mean) * weight).to_numpy(), bad_rate))

    known = host_reputation(pages, outcomes, suffixes).select("host", over("mean", "weight").alias("bad_chance"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, verdict = matched_rule("host", "path", rules)
    rows = rows.join(known, "host").withColumn("rule", rule).withColumn("ruled", verdict)
    by_bound = F.when(F.col("bad_chance") >= sure, "block").otherwise("allow")
    return rows.select("page_id", "host", "path", "rule", F.coalesce("ruled", by_bound).alias("verdict"), "bad_chance")


def outcomes_from_labels(labels: DataFrame) -> DataFrame:
    """The given labels as page outcomes: a page is bad if its row is of low quality or toxic. The ids of pages and labels are taken as one numbering."""
    bad = ((F.col("quality") == 0) | (F.col("toxic") == 1)).cast("long")
    return labels.groupBy(F.col("doc_id").alias("page_id")).agg(F.max(bad).alias("bad"))


ORACLE = r"""
WITH p AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
u AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM p),
o AS (SELECT doc_id AS page_id, max(CASE WHEN quality = 0 OR toxic = 1 THEN 1 ELSE 0 END) AS bad FROM labels GROUP BY doc_id),
h0 AS (SELECT host, count(o.bad) AS n, coalesce(sum(o.bad), 0) AS bad, list_aggregate(list_slice(string_split(host, '.'), -2, -1), 'string_agg', '.') AS two,
              list_aggregate(list_slice(string_split(host, '.'), -3, -1), 'string_agg', '.') AS three, string_split(host, '.')[-1] AS one FROM u LEFT JOIN o USING (page_id) GROUP BY host),
h AS (SELECT host, n, bad, CASE WHEN long THEN three ELSE two END AS domain, CASE WHEN long THEN two ELSE one END AS suffix FROM (SELECT *, two IN (SUFFIX_LIST) AS long FROM h0)),
d AS (SELECT domain, suffix, sum(n) AS n, sum(bad) AS bad FROM h GROUP BY ALL),
s AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad FROM d GROUP BY ALL),
lv AS (SELECT 1 AS lvl, n, bad FROM s UNION ALL SELECT 2, n, bad FROM d UNION ALL SELECT 3, n, bad FROM h),
m AS (SELECT lvl, count(*) AS k, sum(n)::DOUBLE AS nn, sum(bad)::DOUBLE AS bb, sum(bad::DOUBLE * bad / n) AS q, sum((n::DOUBLE) * n) AS r FROM lv WHERE n > 0 GROUP BY lvl),
rho AS (SELECT lvl, CASE WHEN nn - r / nn - (k - 1) > 0
                 THEN ((q - bb * bb / nn) / (((bb + 1) / (nn + 2)) * (1 - (bb + 1) / (nn + 2))) - (k - 1)) / (nn - r / nn - (k - 1)) ELSE 0.5 END AS x FROM m),
st AS (SELECT l.lvl, 1 / greatest(0.001::DOUBLE, least(0.5::DOUBLE, coalesce(x, 0.5::DOUBLE))) - 1 AS k FROM (VALUES (1), (2), (3)) l(lvl) LEFT JOIN rho USING (lvl)),
sp AS (SELECT suffix, (bad + k * (SELECT (coalesce(sum(bad), 0) + 1.0::DOUBLE) / (coalesce(sum(n), 0) + 2.0::DOUBLE) FROM s)) / (n + k) AS m FROM s, st WHERE lvl = 1),
dp AS (SELECT domain, (bad + k * m) / (n + k) AS m FROM d JOIN sp USING (suffix), st WHERE lvl = 2),
hp AS (SELECT host, (bad + k * m) / (n + k) AS m, n + k AS w FROM h JOIN dp USING (domain), st WHERE lvl = 3),
grid AS (SELECT range AS i FROM range(2001)),
-- the integral up to 0.35 of x^(a-1) (1-x)^(b-1), with x = y^(1/a), by Simpson's rule
below AS (SELECT host, sum((CASE WHEN i = 0 OR i = 2000 THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END) * pow(1 - 0.35 * pow(i / 2000.0::DOUBLE, 1 / a), b - 1))
            * pow(0.35::DOUBLE, a) / 2000 / 3 / a * exp(lgamma(a + b) - lgamma(a) - lgamma(b)) AS share
          FROM (SELECT host, m * w AS a, (1 - m) * w AS b FROM hp) q, grid GROUP BY host, a, b),
v AS (SELECT page_id, host, path, share,
        CASE WHEN (host = 'www.example.com' OR host LIKE '%.www.example.com') AND path LIKE '/en/%' THEN 'www.example.com/en/'
             WHEN (host = 'example.com' OR host LIKE '%.example.com') AND path LIKE '/en/%' THEN 'example.com/en/'
             WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/es/%' THEN 'net/es/'
             WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/fr/%' THEN 'net/fr/'
             WHEN (host = 'com' OR host LIKE '%.com') AND path LIKE '/%' THEN 'com/' END AS rule
      FROM u JOIN below USING (host))
SELECT page_id, host, path, rule,
       CASE WHEN rule IN ('www.example.com/en/', 'com/') THEN 'allow' WHEN rule IS NOT NULL THEN 'block'
            WHEN 1 - share >= 0.95 THEN 'block' ELSE 'allow' END AS verdict
FROM v
""".replace("SUFFIX_LIST", ", ".join(f"'{x}'" for x in SUFFIXES))
