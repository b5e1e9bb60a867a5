"""URL filter: host rules, then trust and distrust carried over the link graph between hosts.

A rule (host, path) fits its host and all subdomains where the url's path starts with the rule's; the
longest fitting rule decides. Urls without a rule get the verdict of their host: seeds are the shares
of a host's pages that rules allow or block. Trust is a personalised PageRank from the allowed seeds
along links; distrust one from the blocked seeds against the direction of links, so a host that links to
blocked ones is distrusted. A host is blocked where distrust is above ``LEAST`` and above its trust.

A round joins scores with edges by host and sums by host; the sums are combined before the shuffle and
AQE splits a host with many links. Scores are rounded to 9 decimals, so that reruns agree.

A url that is null or has no ``://`` has an empty host and path, which no rule fits; a null html has no
links; repeated rows count as often as they occur and get equal rows. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Verdict and rule, host and path.
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: Rounds end where no score changes by TOLERANCE; ROUNDS of damping bring any change below it.
DAMPING, ROUNDS, TOLERANCE, LEAST = 0.85, 100, 1e-6, 0.5
LINK = r"""(?i)href\s*=\s*["']?\s*(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'\s>\\]+)"""
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def ruled(pages: DataFrame, rules: tuple = RULES) -> DataFrame:
    """page_id, url, html, host, path, rule and ruling (null where no rule fits)."""
    out = pages.select("page_id", "html", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rule = ruling = None
    for verdict, host, path in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2])):
        fits = ((F.col("host") == host) | F.endswith("host", F.lit("." + host))) & F.startswith("path", F.lit(path))
        rule = F.when(fits, host + path) if rule is None else rule.when(fits, host + path)
        ruling = F.when(fits, verdict) if ruling is None else ruling.when(fits, verdict)
    null = F.lit(None).cast("string")
    return out.withColumn("rule", null if rule is None else rule).withColumn("ruling", null if ruling is None else ruling)


def host_edges(pages: DataFrame) -> DataFrame:
    """src, dst and weight (share of the source's links to other hosts)."""
    links = pages.select(F.col("host").alias("src"), F.explode(F.regexp_extract_all("html", F.lit(LINK), 1)).alias("to"))
    clean = F.translate(F.regexp_replace(F.regexp_replace("to", r"^.*@", ""), r":\d*$", ""), _UPPER, _LOWER)
    n = links.select("src", clean.alias("dst")).where("src <> '' and dst <> '' and src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    n = common.materialise(n)
    return n.join(n.groupBy("src").agg(F.sum("n").alias("all")), "src").select("src", "dst", (F.col("n") / F.col("all")).alias("weight"))


def propagate(seeds: DataFrame, edges: DataFrame, damping: float = DAMPING, rounds: int = ROUNDS, tolerance: float = TOLERANCE) -> DataFrame:
    """host, trust, distrust once no score changes by ``tolerance``, after ``rounds`` rounds at most; seeds: host, trust, distrust.

    Scores are in units of a seed: s + damping * what comes over the edges."""
    edges = common.materialise(edges)
    if edges.isEmpty():
        return seeds
    ways = edges.select(F.col("src").alias("from"), F.col("dst").alias("to"), F.col("weight").alias("t"), F.lit(0.0).alias("d")).unionAll(
        edges.select(F.col("dst").alias("from"), F.col("src").alias("to"), F.lit(0.0).alias("t"), F.col("weight").alias("d")))
    ways = common.materialise(ways)
    start = seeds.unionAll(edges.select(F.explode(F.array("src", "dst")).alias("host"), F.lit(0.0).alias("trust"), F.lit(0.0).alias("distrust")))
    start = common.materialise(start.groupBy("host").agg(F.max("trust").alias("trust"), F.max("distrust").alias("distrust")))
    now = start
    for _ in range(rounds):
        sent = ways.join(now, ways["from"] == now["host"]).select("to", (F.col("t") * F.col("trust")).alias("t"), (F.col("d") * F.col("distrust")).alias("d"))
        come = sent.groupBy("to").agg(F.sum("t").alias("t"), F.sum("d").alias("d"))
        new = start.join(come, start["host"] == come["to"], "left").select(
            "host", *[F.round(F.col(c) + damping * F.coalesce(F.col(x), F.lit(0.0)), 9).alias(c) for c, x in (("trust", "t"), ("distrust", "d"))])
        new = common.materialise(new)
        old = now.toDF("host", "trust_", "distrust_")
        change = new.join(old, "host").agg(F.max(F.greatest(F.abs(F.col("trust") - F.col("trust_")), F.abs(F.col("distrust") - F.col("distrust_"))))).first()[0]
        if now is not start:
            common.forget(now)
        now = new
        if change is None or change < tolerance:
            break
    return now


def judge(pages: DataFrame, rules: tuple = RULES, least: float = LEAST) -> DataFrame:
    """page_id, host, path, rule, verdict, trust and distrust of every page."""
    p = ruled(pages, rules)
    rows = common.materialise(p.select("page_id", "host", "path", "rule", "ruling"))
    share = lambda verdict: F.avg(F.when(F.col("ruling") == verdict, 1.0).otherwise(0.0))
    seeds = common.materialise(rows.groupBy("host").agg(share("allow").alias("trust"), share("block").alias("distrust")))
    scores = propagate(seeds, host_edges(p))
    bad = (F.col("distrust") > least) & (F.col("distrust") > F.col("trust"))
    return rows.join(scores, "host", "left").select(
        "page_id", "host", "path", "rule", F.coalesce("ruling", F.when(bad, "block").otherwise("allow")).alias("verdict"), "trust", "distrust")


def op9_url_trust(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(common.table(spark, sf_dir, "pages"))
