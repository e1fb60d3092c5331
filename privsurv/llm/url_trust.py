"""URL filter: rules first, then link-graph propagation over hosts, in DataFrame operations only.

Hosts of pages that an allow rule fits are trusted seeds, hosts of pages that a block rule fits are distrusted ones,
each weighted by the share of its pages.  Trust is a personalised PageRank along links between hosts, distrust the same
along reversed links (who links to bad hosts is suspect).  A host whose distrust exceeds ``threshold`` times its trust
is blocked, others are allowed; the verdict of a rule always wins for its own pages.

Defined results: null urls, or such without ``://``, have an empty host and path, no rule and verdict allow; relative links stay
within their host and make no edge; repeated pages weigh as often as they occur; without edges scores are the seeds'.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut

RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_parts(url: str = "url") -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url."""
    u = F.coalesce(F.col(url).cast("string"), F.lit(""))
    host = F.translate(F.regexp_extract(u, r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)
    path = F.regexp_extract(u, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)
    return host, path


def fits(host: Column, path: Column, rule: tuple[str, str, str]) -> Column:
    _, name, start = rule
    return ((host == name) | host.endswith(f".{name}")) & path.startswith(start)


def judged(host: Column, path: Column, rules: Sequence[tuple[str, str, str]], what: str) -> Column:
    """The longest fitting rule's text (``what`` = rule) or verdict."""
    out = None
    for rule in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r)):
        value = F.lit(rule[1] + rule[2] if what == "rule" else rule[0])
        out = F.when(fits(host, path, rule), value) if out is None else out.when(fits(host, path, rule), value)
    return F.lit(None).cast("string") if out is None else out


def host_edges(pages: DataFrame) -> DataFrame:
    """Links between different hosts: src, dst, n."""
    host, _ = url_parts()
    links = F.regexp_extract_all(F.coalesce(F.col("html").cast("string"), F.lit("")), F.lit(r"""(?i)href\s*=\s*["']?((?:[a-z][a-z0-9+.-]*:)?//[^"'\s>]+)"""), F.lit(1))
    found = pages.select(host.alias("src"), F.explode(links).alias("link"))
    dst = F.translate(F.regexp_extract("link", r"^[^/]*//([^/?#]*)", 1), UPPER, LOWER)
    return found.select("src", dst.alias("dst")).where("src <> dst and src <> '' and dst <> ''").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def propagate(edges: DataFrame, seeds: DataFrame, damping: float = 0.85, tolerance: float = 1e-9, most: int = 200) -> DataFrame:
    """host, trust, distrust from seeds(host, trust, distrust); each kind of seed weight is scaled to sum to one.

    Rounds go on until ranks change by less than ``tolerance`` in all.  Each round takes 15 % off the distance, so ``most`` rounds
    (1e-14 of it) are never the end of a sound run.
    """
    seeds = cut(seeds, "url-seeds")
    trust, distrust = (x or 1.0 for x in seeds.agg(F.sum("trust"), F.sum("distrust")).first())
    start = seeds.select("host", (F.col("trust") / trust).alias("t0"), (F.col("distrust") / distrust).alias("d0"))
    ranks = start.select("host", F.col("t0").alias("trust"), F.col("d0").alias("distrust"))
    edges = cut(edges, "url-edges")
    if edges.isEmpty():
        return ranks
    out = edges.groupBy("src").agg(F.sum("n").alias("all")).select(F.col("src").alias("from"), "all")
    into = edges.groupBy("dst").agg(F.sum("n").alias("all")).select(F.col("dst").alias("from"), "all")
    steps = cut(
        edges.select(F.col("src").alias("from"), F.col("dst").alias("to"), "n", F.lit(1.0).alias("kind")).join(out, "from")
        .unionByName(edges.select(F.col("dst").alias("from"), F.col("src").alias("to"), "n", F.lit(0.0).alias("kind")).join(into, "from"))
        .select("from", "to", (F.col("n") / F.col("all") * F.col("kind")).alias("wt"), (F.col("n") / F.col("all") * (1 - F.col("kind"))).alias("wd")),
        "url-steps",
    )
    for turn in range(most):
        before = ranks
        sent = steps.join(ranks, steps["from"] == ranks["host"]).groupBy("to").agg(F.sum(F.col("trust") * F.col("wt")).alias("ts"), F.sum(F.col("distrust") * F.col("wd")).alias("ds"))
        ranks = cut(
            start.join(sent, start["host"] == sent["to"], "full").select(
                F.coalesce("host", "to").alias("host"),
                ((1 - damping) * F.coalesce("t0", F.lit(0.0)) + damping * F.coalesce("ts", F.lit(0.0))).alias("trust"),
                ((1 - damping) * F.coalesce("d0", F.lit(0.0)) + damping * F.coalesce("ds", F.lit(0.0))).alias("distrust"),
            ),
            "url-ranks",
        )
        if turn % 4 == 3:
            old = before.select(F.col("host").alias("was"), F.col("trust").alias("t"), F.col("distrust").alias("d"))
            moved = [F.sum(F.abs(F.coalesce(a, F.lit(0.0)) - F.coalesce(b, F.lit(0.0)))) for a, b in (("trust", "t"), ("distrust", "d"))]
            change = ranks.join(old, ranks["host"] == old["was"], "full").agg(*moved).first()
            if max(x or 0.0 for x in change) <= tolerance:
                break
    return ranks


def url_filter(pages: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, threshold: float = 1.0, tolerance: float = 1e-9) -> DataFrame:
    """One row per page: page_id, host, path, rule, verdict, trust, distrust.  ``rules`` is a list of a few hundred at most."""
    if len(rules) > 500:
        raise ValueError("at most 500 rules are compiled into one expression")
    host, path = url_parts()
    named = pages.select("page_id", host.alias("host"), path.alias("path"))
    ruled = named.select("*", judged(F.col("host"), F.col("path"), rules, "rule").alias("rule"), judged(F.col("host"), F.col("path"), rules, "verdict").alias("by_rule"))
    ruled = cut(ruled, "url-pages")
    share = lambda v: F.avg(F.when(F.col("by_rule") == v, 1.0).otherwise(0.0))
    seeds = ruled.groupBy("host").agg(share("allow").alias("trust"), share("block").alias("distrust")).where("host <> ''")
    ranks = propagate(host_edges(pages), seeds, tolerance=tolerance)
    scored = ruled.join(ranks, "host", "left")
    bad = F.coalesce(F.col("distrust"), F.lit(0.0)) > threshold * F.coalesce(F.col("trust"), F.lit(0.0))
    return scored.select(
        "page_id", "host", "path", "rule", F.coalesce("by_rule", F.when(bad, "block").otherwise("allow")).alias("verdict"),
        F.round(F.coalesce("trust", F.lit(0.0)), 12).alias("trust"), F.round(F.coalesce("distrust", F.lit(0.0)), 12).alias("distrust"),
    )
