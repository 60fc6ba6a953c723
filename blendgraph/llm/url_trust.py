"""URL filter: personalised PageRank of trust and reversed distrust over host edges, and rules that overrule it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

# fixed values
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
UPPER, LOWERED = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
HREF = r"""(?i)<a\s[^>]*?href\s*=\s*["']?\s*((?:https?:)?//[^"'\s>]+)"""
#: Score of a seed. Scores are whole numbers of this unit, so sums do not depend on the order of their terms.
UNIT = 100_000_000
MAX_RULES = 500


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path, both empty without '://'."""
    host = F.translate(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")), UPPER, LOWERED)
    return host, F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def longest_rule(host: Column, path: Column, rules: tuple[tuple[str, str], ...] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null if none does."""
    if len(rules) > MAX_RULES:
        raise ValueError(f"{len(rules)} rules; this form takes {MAX_RULES}")
    rule = verdict = F.lit(None).cast("string")
    for what, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        own_host, slash, own_path = text.partition("/")
        fits = ((host == own_host) | host.endswith("." + own_host)) & path.startswith(slash + own_path)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def host_edges(pages: DataFrame) -> DataFrame:
    """pages(host, html) -> distinct (src, dst): links between hosts, and both ways between a host and the host one label
    shorter, if that has three labels or more (www.a.example.com and a.example.com are one site). Links without a host
    stay on theirs and make no edge."""
    targets = F.array_distinct(F.transform(F.regexp_extract_all("html", F.lit(HREF), 1), lambda u: F.translate(F.regexp_extract(u, r"//([^/?#]*)", 1), UPPER, LOWERED)))
    links = pages.select(F.col("host").alias("src"), F.explode(targets).alias("dst")).filter("src <> dst AND src <> '' AND dst <> ''").distinct()
    nodes = pages.select("host").distinct().unionByName(links.select(F.col("dst").alias("host"))).distinct()
    site = nodes.select(F.col("host").alias("src"), F.regexp_extract("host", r"^[^.]+\.([^.]+\.[^.]+\..+)$", 1).alias("dst")).filter("dst <> ''")
    return links.unionByName(site).unionByName(site.selectExpr("dst AS src", "src AS dst")).distinct()


def propagate(edges: DataFrame, seeds: DataFrame, rounds: int = 10, damping_percent: int = 85) -> DataFrame:
    """edges(kind, src, dst), seeds(kind, host) -> (kind, host, score): personalised PageRank of each kind.

    Every seed gives UNIT; a host passes damping_percent of its score on, in equal parts by whole-number division, to
    the hosts it has edges to; seeds get the rest of UNIT anew in each round. A hub's edges join with its one score.
    Rounds are written to the shared folder every fifth time.
    """
    edges = written(edges, "edges")
    degree = written(edges.groupBy("kind", "src").agg(F.count("*").alias("n")), "degrees")
    paths = written(edges.join(degree, ["kind", "src"]).select("kind", "src", "dst", "n"), "host-edges")
    source = written(seeds.select("kind", "host").distinct(), "seeds")
    fresh = source.select("kind", "host", F.lit(UNIT * (100 - damping_percent) // 100).cast("long").alias("score"))
    scores = source.select("kind", "host", F.lit(UNIT).cast("long").alias("score"))
    for i in range(1, rounds + 1):
        sent = scores.withColumnRenamed("host", "src").join(paths, ["kind", "src"])
        sent = sent.select("kind", F.col("dst").alias("host"), F.expr(f"score * {damping_percent} div (100 * n)").alias("score"))
        scores = sent.unionByName(fresh).groupBy("kind", "host").agg(F.sum("score").alias("score"))
        if i % 5 == 0 and i < rounds:
            scores = written(scores, "scores")
    return scores


def judge_urls(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, block_share_percent: int = 50, rounds: int = 10) -> DataFrame:
    """page_id, host, path, rule, verdict, trust and distrust of every row of pages(page_id, url, html).

    Hosts with a page that an allow rule fits are the trusted seeds, those with a blocked page the blocked ones; trust
    runs along the edges, distrust against them. Without a fitting rule a page is blocked if its host's distrust is over
    block_share_percent of its trust and distrust together, else allowed. Null url: no host, no path, allowed.
    Of rules of equal length the last by name wins. Null or empty html: no links; a long one is read once. Repeated rows are judged each; extra columns are ignored; an empty table gives no rows.
    """
    host, path = url_parts(F.col("url"))
    p = pages.select("page_id", host.alias("host"), path.alias("path"), "html")
    rule, verdict = longest_rule(F.col("host"), F.col("path"), rules)
    judged = p.select("page_id", "host", "path", rule.alias("rule"), verdict.alias("ruled"))
    edges = host_edges(p.select("host", "html"))
    both = edges.select(F.lit(0).alias("kind"), "src", "dst").unionByName(edges.select(F.lit(1).alias("kind"), F.col("dst").alias("src"), F.col("src").alias("dst")))
    seeds = judged.filter("ruled IS NOT NULL AND host <> ''").select(F.expr("IF(ruled = 'allow', 0, 1)").alias("kind"), "host").distinct()
    scores = propagate(both, seeds, rounds).groupBy("host").agg(*[F.coalesce(F.sum(F.when(F.col("kind") == k, F.col("score"))), F.lit(0)).alias(name) for k, name in ((0, "trust"), (1, "distrust"))])
    # written first, so that the pages of a large host come by an exchange of their own and can be split
    out = judged.join(written(scores, "host-scores"), "host", "left").fillna(0, ["trust", "distrust"])
    method = F.when(F.col("distrust") * 100 > (F.col("trust") + F.col("distrust")) * block_share_percent, "block").otherwise("allow")
    return out.select("page_id", "host", "path", "rule", F.coalesce("ruled", method).alias("verdict"), "trust", "distrust")
