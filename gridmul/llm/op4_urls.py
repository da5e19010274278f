"""URL filters: explicit rules first, then link-graph propagation.

Hosts are the nodes, links between different hosts the edges. Trust is personalised PageRank from hosts that an allow rule
names, distrust the same walk over the reversed edges from hosts that a block rule names; a host whose distrust outweighs
its trust is blocked, however small both are. Mass of hosts without links goes back to the seeds: such a walk is the one that
loses that mass, scaled to one in all. Steps go on until no host's score changes by more than TOLERANCE of itself, so the walk
reaches every host that links lead to. Each step is one join and one aggregation over the edge table and one join for the
change; nothing of the graph is collected.

Defined cases: a null URL, or one without `://`, has an empty host and path, fits no rule and is allowed unless its (empty)
host is judged otherwise; null HTML has no links; very long URLs, tags and pages are read whole (a tag ends at its first `>`);
relative links stay on their host and are no edges; repeated links count once per page; a host whose distrust equals its trust
is allowed; of rules of one length the last of the alphabet wins, which only repeated rules can be; repeated rows are judged alike;
an empty table gives an empty result; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import materialise

#: (verdict, host, path) of the contract.
RULES = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]

DAMPING = 0.85
#: Relative change of a host's score below which the walk has converged.
TOLERANCE = 1e-6
#: A host is blocked where distrust > trust * BLOCK_RATIO (shares of all mass).
BLOCK_RATIO = 1.0
#: A link to another host or scheme; group 1 is the host.
LINK = r"""(?i)<a\s(?:[^>]*?\s)?href\s*=\s*["']?(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'\s>]+)"""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: list[tuple[str, str, str]] = RULES) -> tuple[Column, Column]:
    """(rule, its verdict): the longest rule whose host is the url's or a parent domain and whose path begins it."""
    rule = verdict = F.lit(None).cast("string")
    for what, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1] + r[2])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule = F.when(fits, F.lit(h + p)).otherwise(rule)
        verdict = F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def host_edges(pages: DataFrame, host: str = "host", html: str = "html") -> DataFrame:
    """(src, dst, pages): links between different hosts; a page counts once for each target host."""
    links = F.array_distinct(F.transform(F.regexp_extract_all(F.coalesce(F.col(html), F.lit("")), F.lit(LINK), 1), lambda h: F.translate(h, _UPPER, _LOWER)))
    return pages.select(F.col(host).alias("src"), F.explode(links).alias("dst")).where("src <> '' AND dst <> src").groupBy("src", "dst").agg(F.count("*").alias("pages"))


def propagate(edges: DataFrame, seeds: DataFrame, damping: float = DAMPING, label: str = "rank", tolerance: float = TOLERANCE) -> DataFrame:
    """Personalised PageRank: (host, score). seeds: (host, seed), with seed summing to 1; edges: (src, dst, weight).

    One join and one aggregation a step; the scores are written after each, to cut lineage and to be compared."""
    out = edges.groupBy("src").agg(F.sum("weight").alias("total"))
    shares = materialise(edges.join(out, "src").select("src", "dst", (F.col("weight") / F.col("total")).alias("share")), f"{label}-edges", narrow=True)
    score = seeds.select("host", F.col("seed").alias("score"))
    if shares.isEmpty():  # no edge: every step leaves the seeds' share as it is
        return score
    while True:
        moved = shares.join(score, shares.src == score.host).select(F.col("dst").alias("host"), (F.col("share") * F.col("score") * damping).alias("x"))
        kept = seeds.select("host", (F.col("seed") * (1 - damping)).alias("x"))
        before, score = score, materialise(moved.unionByName(kept).groupBy("host").agg(F.sum("x").alias("score")), label, narrow=True)
        both = score.join(before.select("host", F.col("score").alias("before")), "host", "left")
        if both.where(F.abs(F.col("score") - F.coalesce("before", F.lit(0.0))) > F.col("score") * tolerance).isEmpty():
            break
    total = score.agg(F.sum("score")).first()[0]
    return score.select("host", (F.col("score") / F.lit(total or 1.0)).alias("score"))


def host_scores(pages: DataFrame) -> DataFrame:
    """(host, trust, distrust) from pages with host, html and rule_verdict."""
    edges = materialise(host_edges(pages), "links", narrow=True)
    hosts = materialise(pages.groupBy("host").agg(F.count(F.when(F.col("rule_verdict") == "allow", 1)).alias("good"), F.count(F.when(F.col("rule_verdict") == "block", 1)).alias("bad")), "hosts", narrow=True)
    total = hosts.agg(F.sum("good").alias("good"), F.sum("bad").alias("bad")).first()

    def seeds(kind: str) -> DataFrame:
        return hosts.where(F.col(kind) > 0).select("host", (F.col(kind) / F.lit(float(total[kind] or 1))).alias("seed"))

    trust = propagate(edges.select("src", "dst", F.col("pages").alias("weight")), seeds("good"), label="trust")
    distrust = propagate(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("pages").alias("weight")), seeds("bad"), label="distrust")
    both = hosts.select("host").join(trust.withColumnRenamed("score", "trust"), "host", "left").join(distrust.withColumnRenamed("score", "distrust"), "host", "left")
    return both.select("host", F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))


def filter_urls(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, host, path, rule, verdict, trust, distrust): a rule's verdict where one fits, else the host's."""
    url = F.col(url_col).cast("string")
    base = pages.select(F.col(id_col).alias("page_id"), host_of(url).alias("host"), path_of(url).alias("path"), F.col(html_col).cast("string").alias("html"))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    base = base.withColumn("rule", rule).withColumn("rule_verdict", verdict)
    scores = materialise(host_scores(base), "scores", narrow=True)
    bad = F.col("distrust") > F.col("trust") * BLOCK_RATIO
    joined = base.drop("html").join(scores, "host", "left")
    return joined.select("page_id", "host", "path", "rule", F.coalesce("rule_verdict", F.when(bad, "block").otherwise("allow")).alias("verdict"), "trust", "distrust")
