"""URL filter: fixed rules first, else empirical-Bayes reputation of hosts.

Labelled page outcomes (good or not) are counted by host. A beta-binomial prior is fitted at every level by
moments: suffixes shrink to the corpus, registered domains to their suffix, hosts to their domain. A page is
allowed if the lower bound of its host's posterior (mean minus z standard deviations) reaches the threshold.
Hosts without labels inherit their domain's posterior. Only DataFrame and SQL functions are used.

Defined results: a null url or one without ``://`` has empty host and path and gets the corpus-wide verdict of the
empty host; labels that are null or name no page are ignored; repeated pages count once for each row; an
empty page table gives an empty result; without any label the prior is beta(1, 1).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from bspframe.llm.line_dedup import LOWER, UPPER
from bspframe.session import materialise

#: (host, path, verdict)
RULES = (("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block"))
#: Suffixes of two labels (fixed values; a full public list can be passed instead).
TWO_LABEL_SUFFIXES = ("co.uk", "org.uk", "ac.uk", "gov.uk", "com.au", "net.au", "org.au", "co.jp", "ne.jp", "or.jp", "com.br", "co.in", "co.nz", "co.za", "com.cn", "com.mx", "com.tr", "co.kr")
Z, THRESHOLD = 1.645, 0.7
#: Limits of a fitted prior's weight.
LEAST, MOST = 1.0, 10_000.0


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path as columns."""
    u = F.coalesce(url.cast("string"), F.lit(""))
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    return F.translate(F.regexp_extract(u, pattern, 1), UPPER, LOWER), F.regexp_extract(u, pattern, 2)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest fitting rule as a string and its verdict; of equally long ones that with the longer host."""
    name = verdict = F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: (len(r[0] + r[1]), len(r[0]))):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        name = F.when(fits, h + p).otherwise(name)
        verdict = F.when(fits, v).otherwise(verdict)
    return name, verdict


def levels(host: Column, two_label: tuple[str, ...] = TWO_LABEL_SUFFIXES) -> tuple[Column, Column]:
    """Registered domain and suffix of a host; ports do not count, addresses are their own domain."""
    bare = F.regexp_replace(host, ":[0-9]*$", "")
    number = bare.rlike(r"^[0-9.]+$") | bare.contains(":")
    two = F.substring_index(bare, ".", -2)
    deep = two.isin(*two_label) if two_label else F.lit(False)
    suffix = F.when(number, "").when(deep, two).otherwise(F.substring_index(bare, ".", -1))
    domain = F.when(number, bare).when(deep, F.substring_index(bare, ".", -3)).otherwise(two)
    return domain, suffix


def _weight(children: DataFrame, prior: str) -> float:
    """Weight of the beta prior by moments: spread of children's rates about their priors against sampling noise."""
    r = children.where("n > 0").select(
        F.sum("n").alias("n"),
        F.count("*").alias("g"),
        F.sum(F.expr(f"n * pow(y / n - {prior}, 2)")).alias("s"),
        F.sum(F.expr(f"n * {prior} * (1 - {prior})")).alias("v"),
    ).first()
    if not r["n"] or not r["v"]:
        return LEAST
    v, s, noise = r["v"] / r["n"], r["s"] / r["n"], r["v"] / r["n"] * r["g"] / r["n"]
    return MOST if s <= noise else min(MOST, max(LEAST, (v - s) / (s - noise)))


def host_reputation(outcomes: DataFrame) -> DataFrame:
    """``outcomes(host, good)`` (good null: not labelled) → host, domain, suffix, n, y, mean, deviation."""
    domain, suffix = levels(F.col("host"))
    hosts = outcomes.groupBy("host").agg(F.count("good").alias("n"), F.coalesce(F.sum("good"), F.lit(0)).cast("long").alias("y"))
    hosts = materialise(hosts.withColumn("domain", domain).withColumn("suffix", suffix), "hosts")  # pages are counted once
    total = hosts.agg(F.sum("n"), F.sum("y")).first()
    base = (total[1] + 1) / (total[0] + 2) if total[0] is not None else 0.5
    up = lambda df, *keys: df.groupBy(*keys).agg(F.sum("n").alias("n"), F.sum("y").alias("y"))
    suffixes = up(hosts, "suffix").withColumn("prior", F.lit(base))
    m = _weight(suffixes, "prior")
    suffixes = suffixes.select("suffix", F.expr(f"(y + {m!r} * prior) / (n + {m!r})").alias("prior"))
    domains = up(hosts, "suffix", "domain").join(suffixes, "suffix")
    m = _weight(domains, "prior")
    domains = domains.select("suffix", "domain", F.expr(f"(y + {m!r} * prior) / (n + {m!r})").alias("prior"))
    hosts = hosts.join(domains, ["suffix", "domain"])
    m = _weight(hosts, "prior")
    hosts = hosts.withColumn("mean", F.expr(f"(y + {m!r} * prior) / (n + {m!r})"))
    return hosts.withColumn("deviation", F.expr(f"sqrt(mean * (1 - mean) / (n + {m!r} + 1))")).drop("prior")


def _judged(pages: DataFrame, labels: DataFrame, rules, z: float, threshold: float) -> DataFrame:
    """``pages(row, page_id, url)`` → row, page_id, host, path, rule, verdict, bound."""
    host, path = url_parts(F.col("url"))
    seen = pages.select("row", "page_id", host.alias("host"), path.alias("path"))
    marks = labels.where("page_id is not null and good is not null").groupBy("page_id").agg(F.max("good").cast("long").alias("good"))
    reputation = host_reputation(seen.select("page_id", "host").join(marks, "page_id", "left").select("host", "good"))
    bound = reputation.select("host", (F.col("mean") - z * F.col("deviation")).alias("bound"))
    rule, fixed = rule_of(F.col("host"), F.col("path"), rules)
    return seen.join(bound, "host").select("row", "page_id", "host", "path", rule.alias("rule"), F.coalesce(fixed, F.when(F.col("bound") >= threshold, "allow").otherwise("block")).alias("verdict"), F.round("bound", 6).alias("bound"))


def judge(pages: DataFrame, labels: DataFrame, rules=RULES, z: float = Z, threshold: float = THRESHOLD) -> DataFrame:
    """``pages(page_id, url)`` and ``labels(page_id, good)`` → page_id, host, path, rule, verdict, bound."""
    return _judged(pages.select(F.lit(None).alias("row"), "page_id", "url"), labels, rules, z, threshold).drop("row")


def filter_urls(pages: DataFrame, labels: DataFrame, rules=RULES, z: float = Z, threshold: float = THRESHOLD) -> DataFrame:
    """The pages that are allowed, each row judged by its own url, whatever ids repeat or are null."""
    rows = pages.select(F.struct("*").alias("row"), "page_id", "url")
    return _judged(rows, labels, rules, z, threshold).where("verdict = 'allow'").select("row.*")


def oracle(rules=RULES, z: float = Z, threshold: float = THRESHOLD) -> str:
    order = sorted(rules, key=lambda r: (-len(r[0] + r[1]), -len(r[0])))
    fits = lambda h, p: f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))"
    name = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{h + p}'" for h, p, _ in order) + " END"
    verdict = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{v}'" for h, p, v in order) + " END"
    two = ", ".join(f"'{s}'" for s in TWO_LABEL_SUFFIXES)
    moments = lambda t: f"""(SELECT CASE WHEN sum(n) IS NULL OR sum(n * prior * (1 - prior)) = 0 THEN {LEAST}
      WHEN sum(n * pow(y / n - prior, 2)) / sum(n) <= sum(n * prior * (1 - prior)) / sum(n) * count(*) / sum(n) THEN {MOST}
      ELSE least({MOST}, greatest({LEAST}, (sum(n * prior * (1 - prior)) / sum(n) - sum(n * pow(y / n - prior, 2)) / sum(n))
        / (sum(n * pow(y / n - prior, 2)) / sum(n) - sum(n * prior * (1 - prior)) / sum(n) * count(*) / sum(n)))) END AS m
      FROM {t} WHERE n > 0)"""  # noqa: E731
    return f"""
WITH parts AS (
  SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), '{UPPER}', '{LOWER}') AS host,
         regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path FROM pages),
marks AS (SELECT doc_id, max(quality) AS good FROM labels WHERE doc_id IS NOT NULL AND quality IS NOT NULL GROUP BY doc_id),
counts AS (
  SELECT host, count(good)::DOUBLE AS n, coalesce(sum(good), 0)::DOUBLE AS y, string_split(regexp_replace(host, ':[0-9]*$', ''), '.') AS l
  FROM parts LEFT JOIN marks ON page_id = doc_id GROUP BY host),
shapes AS (SELECT *, array_to_string(l, '.') AS bare, array_to_string(l[-2:], '.') AS two FROM counts),
hosts AS (
  SELECT host, n, y,
    CASE WHEN regexp_matches(bare, '^[0-9.]+$') OR contains(bare, ':') THEN bare WHEN two IN ({two}) THEN array_to_string(l[-3:], '.') ELSE two END AS domain,
    CASE WHEN regexp_matches(bare, '^[0-9.]+$') OR contains(bare, ':') THEN '' WHEN two IN ({two}) THEN two ELSE l[-1] END AS suffix
  FROM shapes),
s0 AS (SELECT suffix, sum(n) AS n, sum(y) AS y, (SELECT (sum(y) + 1) / (sum(n) + 2) FROM hosts) AS prior FROM hosts GROUP BY suffix),
s1 AS (SELECT suffix, (y + m * prior) / (n + m) AS prior FROM s0, {moments('s0')}),
d0 AS (SELECT suffix, domain, sum(n) AS n, sum(y) AS y, any_value(prior) AS prior FROM hosts JOIN s1 USING (suffix) GROUP BY suffix, domain),
d1 AS (SELECT suffix, domain, (y + m * prior) / (n + m) AS prior FROM d0, {moments('d0')}),
h0 AS (SELECT host, n, y, prior FROM hosts JOIN d1 USING (suffix, domain)),
h1 AS (SELECT host, n, m, (y + m * prior) / (n + m) AS mean FROM h0, {moments('h0')}),
bounds AS (SELECT host, mean - {z} * sqrt(mean * (1 - mean) / (n + m + 1)) AS bound FROM h1)
SELECT page_id, host, path, {name} AS rule, coalesce({verdict}, CASE WHEN bound >= {threshold} THEN 'allow' ELSE 'block' END) AS verdict,
  round(bound, 6) AS bound
FROM parts JOIN bounds USING (host)
"""
