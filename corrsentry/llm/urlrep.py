"""URL filter by empirical-Bayes host reputation, in DataFrame functions only.

Labelled page outcomes are counted for each host; beta-binomial priors shrink them level by level: the suffix is
shrunk to the corpus, the registered domain to its suffix, the host to its domain.  A host is blocked if the lower
bound of its posterior good rate is under `floor`.  Hand-written (host, path) rules come first; the longest wins.

Edge cases: a null url, or one without `://`, has an empty host and path, fits no rule and is judged as the host ''.
Hosts without labelled pages have their domain's prior.  Labels without a page are ignored, several labels of a page
all count, repeated page rows are judged alike.  Empty tables give an empty result.  Other columns are ignored.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import even_join, table, written


class Rule(NamedTuple):
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules of the query's contract.
RULES = [Rule("allow", "com", "/"), Rule("block", "example.com", "/en/"), Rule("allow", "www.example.com", "/en/"), Rule("block", "net", "/es/"), Rule("block", "net", "/fr/")]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Suffixes of two labels under which names are registered; any other suffix is the last label.
TWO_LABEL_SUFFIXES = ["ac.uk", "co.jp", "co.uk", "com.au", "com.br", "gov.uk", "org.uk"]


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path): what stands after the first `://` up to `/ ? #`, A-Z lower-cased; then up to `? #`."""
    after = F.coalesce(F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1), F.lit(""))
    host = F.translate(F.regexp_extract(after, r"^([^/?#]*)", 1), UPPER, LOWER)
    return host, F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1)


def registered(host: Column) -> tuple[Column, Column]:
    """(registered domain, suffix) of a host; a host of one label is its own domain."""
    bare = F.regexp_replace(host, r":\d*$", "")
    two = F.substring_index(bare, ".", -2)
    suffix = F.when(two.isin(TWO_LABEL_SUFFIXES), two).otherwise(F.substring_index(bare, ".", -1))
    domain = F.when(two.isin(TWO_LABEL_SUFFIXES), F.substring_index(bare, ".", -3)).otherwise(two)
    return domain, suffix


def matched_rule(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """(name, verdict) of the longest rule that fits, or nulls."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.name), r.name)):  # later wins
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        name, verdict = F.when(fits, r.name).otherwise(name), F.when(fits, r.verdict).otherwise(verdict)
    return name, verdict


def strength(units: DataFrame) -> Column:
    """Beta-binomial prior strength of the rates good/n of `units` by moments, between 2 and 1000 pseudo-pages."""
    n, g, k = F.sum("n"), F.sum("good"), F.count(F.lit(1))
    p = g / n
    within = F.sum(F.col("good") * F.col("good") / F.col("n"))
    between = within - g * g / n  # weighted sum of squares of the rates around the overall one
    scale = n - F.sum(F.col("n") * F.col("n")) / n
    excess = (between - (k - 1) * p * (1 - p)) / scale
    rho = excess / (p * (1 - p))
    return F.when((n > 0) & (scale > 0) & (p * (1 - p) > 0) & (rho > 0), F.least(F.greatest(1 / rho - 1, F.lit(2.0)), F.lit(1000.0))).otherwise(F.lit(1000.0)).alias("m")


def reputation(hosts: DataFrame, z: float = 1.645) -> DataFrame:
    """host (key), n, good -> posterior mean and bound.  hosts: one row for each host; the levels are aggregated from
    it, so no step sees single pages.  The prior strengths and the overall rate are four numbers, which the driver reads."""
    domain, suffix = registered(F.col("host"))
    h = hosts.select("host", domain.alias("domain"), suffix.alias("suffix"), "n", "good")
    d = h.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    s = d.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    m0, m1, m2 = (x.where("n > 0").agg(strength(x)).first()["m"] for x in (h, d, s))
    p_all = s.agg(((F.coalesce(F.sum("good"), F.lit(0)) + 1.0) / (F.coalesce(F.sum("n"), F.lit(0)) + 2.0)).alias("p")).first()["p"]
    s = s.select("suffix", ((F.col("good") + m2 * p_all) / (F.col("n") + m2)).alias("p_s"))
    d = d.join(s, "suffix").select("domain", ((F.col("good") + m1 * F.col("p_s")) / (F.col("n") + m1)).alias("p_d"))
    out = h.join(d, "domain")
    a, b = F.col("good") + m0 * F.col("p_d"), F.col("n") - F.col("good") + m0 * (1 - F.col("p_d"))
    mean, sd = a / (a + b), F.sqrt(a * b / ((a + b) * (a + b) * (a + b + 1)))
    return out.select("host", "n", "good", mean.alias("good_rate"), (mean - z * sd).alias("bound"))


def url_filter(pages: DataFrame, outcomes: DataFrame, rules: list[Rule] = RULES, floor: float = 0.5, z: float = 1.645) -> DataFrame:
    """pages (page_id, url) -> page_id, host, path, rule, verdict, good_rate, bound.  outcomes: page_id, good (0 or 1).

    Outcomes are joined by page and summed by host before any host-level join, so a host with a third of all pages
    is one row there; the hosts are written once for all levels, and the last join, of hosts to pages, salts hot hosts."""
    host, path = split_url(F.col("url"))
    urls = pages.select("page_id", host.alias("host"), path.alias("path"))
    seen = outcomes.where(F.col("good").isNotNull()).groupBy("page_id").agg(F.count(F.lit(1)).alias("n"), F.sum("good").alias("good"))
    hosts = urls.join(seen, "page_id", "left").groupBy("host").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("good"), F.lit(0)).alias("good"), F.count(F.lit(1)).alias("c"))
    hosts = written(hosts, "hosts")
    rated = reputation(hosts, z)
    rule, by_rule = matched_rule(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("bound") < floor, "block").otherwise("allow")
    return even_join(urls, rated, ["host"], sizes=hosts).select("page_id", "host", "path", rule.alias("rule"), F.coalesce(by_rule, own).alias("verdict"), "good_rate", "bound")


def op9_url_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcome of a page: good if the label of its id has quality 1 and toxic 0."""
    y = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), ((F.col("quality") == 1) & (F.col("toxic") == 0)).cast("int").alias("good"))
    return url_filter(table(spark, sf_dir, "pages"), y).select("page_id", "host", "path", "rule", "verdict")


_SUFFIX = ", ".join(f"'{x}'" for x in TWO_LABEL_SUFFIXES)
_STRENGTH = """(SELECT CASE WHEN sum(n) > 0 AND sum(n) - sum(n * n) / sum(n)::DOUBLE > 0 AND sum(good) > 0 AND sum(good) < sum(n)
 AND ((sum(good * good / n::DOUBLE) - sum(good) * sum(good) / sum(n)::DOUBLE - (count(*) - 1) * (sum(good) / sum(n)::DOUBLE) * (1 - sum(good) / sum(n)::DOUBLE)) / (sum(n) - sum(n * n) / sum(n)::DOUBLE)) > 0
 THEN least(greatest(1 / (((sum(good * good / n::DOUBLE) - sum(good) * sum(good) / sum(n)::DOUBLE - (count(*) - 1) * (sum(good) / sum(n)::DOUBLE) * (1 - sum(good) / sum(n)::DOUBLE)) / (sum(n) - sum(n * n) / sum(n)::DOUBLE)) / ((sum(good) / sum(n)::DOUBLE) * (1 - sum(good) / sum(n)::DOUBLE))) - 1, 2.0), 1000.0)
 ELSE 1000.0 END FROM {} WHERE n > 0)"""
_FITS = [f"WHEN (host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}') THEN '{{}}{r.name}'" for r in sorted(RULES, key=lambda r: (-len(r.name), r.name))]
SQL = f"""
WITH cut AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS a FROM pages),
urls AS (SELECT page_id, translate(regexp_extract(a, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}') AS host, regexp_extract(a, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
seen AS (SELECT doc_id AS page_id, count(*) AS n, sum(CASE WHEN quality = 1 AND toxic = 0 THEN 1 ELSE 0 END)::BIGINT AS good FROM labels WHERE quality IS NOT NULL AND toxic IS NOT NULL GROUP BY 1),
hosts AS (SELECT host, coalesce(sum(n), 0)::BIGINT AS n, coalesce(sum(good), 0)::BIGINT AS good FROM urls LEFT JOIN seen USING (page_id) GROUP BY 1),
parts AS (SELECT *, string_split(regexp_replace(host, ':[0-9]*$', ''), '.') AS p FROM hosts),
h AS (SELECT host, n, good, array_to_string(p[-2:], '.') AS two, p FROM parts),
l AS (SELECT host, n, good, CASE WHEN two IN ({_SUFFIX}) THEN array_to_string(p[-3:], '.') ELSE two END AS domain, CASE WHEN two IN ({_SUFFIX}) THEN two ELSE p[-1] END AS suffix FROM h),
d AS (SELECT domain, suffix, sum(n)::BIGINT AS n, sum(good)::BIGINT AS good FROM l GROUP BY 1, 2),
s AS (SELECT suffix, sum(n)::BIGINT AS n, sum(good)::BIGINT AS good FROM d GROUP BY 1),
m AS (SELECT {_STRENGTH.format('l')} AS m0, {_STRENGTH.format('d')} AS m1, {_STRENGTH.format('s')} AS m2, (SELECT (sum(good) + 1.0::DOUBLE) / (sum(n) + 2.0::DOUBLE) FROM s) AS p_all),
ps AS (SELECT suffix, (good + m2 * p_all) / (n + m2) AS p_s FROM s, m),
pd AS (SELECT domain, (good + m1 * p_s) / (n + m1) AS p_d FROM d JOIN ps USING (suffix), m),
ab AS (SELECT host, good + m0 * p_d AS a, n - good + m0 * (1 - p_d) AS b FROM l JOIN pd USING (domain), m),
rated AS (SELECT host, a / (a + b) - 1.645::DOUBLE * sqrt(a * b / ((a + b) * (a + b) * (a + b + 1))) AS bound FROM ab),
judged AS (SELECT page_id, host, path, bound, CASE {' '.join(x.format('') for x in _FITS)} ELSE NULL END AS rule FROM urls JOIN rated USING (host))
SELECT page_id, host, path, rule, CASE {' '.join(f"WHEN rule = '{r.name}' THEN '{r.verdict}'" for r in RULES)} WHEN bound < 0.5 THEN 'block' ELSE 'allow' END AS verdict FROM judged
"""
