"""URL verdicts from rules and from trust that flows over host links (built-in functions only).

Rules name a host and the start of a path; they hold for subdomains, and the
longest that fits decides. Elsewhere the host decides. Personalised PageRank
runs twice over the edges between hosts that page links make: trust starts at
hosts with allowed pages and follows links; distrust starts at hosts with
blocked pages and runs against links (who links to them is suspect). A host is
blocked when its distrust passes ``block_ratio`` times its trust and the floor
``1 / hosts * least``; without evidence it is allowed. Ranks are taken to a tenth of that
floor, so no host is too far from a seed to be judged.

Defined results: a null url, or one without ``://``, has empty host and path,
no rule, and is allowed; links of rows without host are not followed; equal
rows are judged alike; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop, park

#: (verdict, host, start of path), in the order given by their owner.
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
#: Rules become one expression; a longer list belongs in a table joined by host suffix.
MOST_RULES = 500
#: Rounds of propagation in one job.
STEPS = 4
CAPITALS, SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    after = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(after, CAPITALS, SMALL)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> tuple[Column, Column]:
    """The longest fitting rule's text and verdict; null where none fits."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"at most {MOST_RULES} rules")
    text = verdict = F.lit(None).cast("string")
    for what, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = (host != "") & ((host == h) | F.endswith(host, F.lit(f".{h}"))) & F.startswith(path, F.lit(p))
        text, verdict = F.when(fits, f"{h}{p}").otherwise(text), F.when(fits, what).otherwise(verdict)
    return text, verdict


def host_edges(pages: DataFrame) -> DataFrame:
    """Distinct edges (src, dst) between hosts, from absolute and scheme-relative links."""
    links = pages.select(host_of(F.col("url")).alias("src"), F.explode(F.regexp_extract_all("html", F.lit(r"""(?i)href\s*=\s*["']?\s*((?:https?:)?//[^\s"'<>]+)"""), F.lit(1))).alias("link"))
    to = host_of(F.when(F.startswith("link", F.lit("//")), F.concat(F.lit("http:"), "link")).otherwise(F.col("link")))
    return links.select("src", to.alias("dst")).where("src <> '' and dst <> '' and src <> dst").distinct()


def propagate(hosts: DataFrame, edges: DataFrame, seed: str, source: str, target: str, damping: float = 0.85, tolerance: float = 1e-6) -> DataFrame:
    """Personalised PageRank along source -> target from the hosts' ``seed`` column, until a
    round changes no more than ``tolerance`` in all (which the damping brings about).

    What a host without such edges holds goes back to the seeds. That only scales the ranks,
    so rounds let it go and the sum is set to one at the end: no round waits for the driver,
    and ``STEPS`` of them make one job.
    """
    degree = edges.groupBy(source).agg(F.count("*").alias("degree"))
    weighted = park(edges.join(degree, source).select(F.col(source).alias("from"), F.col(target).alias("to"), "degree"), "weighted")
    total = hosts.agg(F.sum(seed)).head()[0] or 0.0
    if not total:
        return hosts.select("host", F.lit(0.0).alias("mass"))
    start = F.col(seed) / F.lit(float(total)) * (1 - damping)
    mass = park(hosts.select("host", start.alias("start"), start.alias("mass"), F.lit(0.0).alias("old")), "mass")
    for _ in range(math.ceil(math.log(tolerance) / math.log(damping) / STEPS) + 1):
        new = mass
        for _ in range(STEPS):
            sent = weighted.join(new, weighted["from"] == new["host"]).groupBy("to").agg(F.sum(F.col("mass") / F.col("degree")).alias("got"))
            gained = F.lit(damping) * F.coalesce("got", F.lit(0.0)) + F.col("start")
            new = new.join(sent, new["host"] == sent["to"], "left").select("host", "start", gained.alias("mass"), F.col("mass").alias("old"))
        new = park(new, "mass")
        drop(mass)
        mass = new
        if (mass.agg(F.sum(F.abs(F.col("mass") - F.col("old")))).head()[0] or 0.0) <= tolerance:
            break
    drop(weighted)
    whole = mass.agg(F.sum("mass")).head()[0]
    return mass.select("host", (F.col("mass") / F.lit(float(whole))).alias("mass"))


def judge_urls(pages: DataFrame, rules: tuple = RULES, block_ratio: float = 1.0, least: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, trust, distrust."""
    parts = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    parts = parts.withColumns({"rule": rule, "told": verdict})
    edges = park(host_edges(pages), "edges")
    seen = parts.where("host <> ''").groupBy("host").agg(F.count_if(F.col("told") == "allow").alias("good"), F.count_if(F.col("told") == "block").alias("bad"), F.count("*").alias("n"))
    other = edges.select(F.col("dst").alias("host")).distinct().join(seen, "host", "left_anti").select("host", F.lit(0).alias("good"), F.lit(0).alias("bad"), F.lit(1).alias("n"))
    hosts = park(seen.union(other).select("host", (F.col("good") / F.col("n")).alias("good"), (F.col("bad") / F.col("n")).alias("bad")), "hosts")
    n = hosts.count()
    close = 0.1 * least / max(n, 1)
    trust = propagate(hosts, edges, "good", "src", "dst", tolerance=close).withColumnRenamed("mass", "trust")
    doubt = propagate(hosts, edges, "bad", "dst", "src", tolerance=close).withColumnRenamed("mass", "distrust")
    rated = trust.join(doubt, "host")
    blocked = (F.col("distrust") > F.col("trust") * block_ratio) & (F.col("distrust") >= F.lit(least / max(n, 1)))
    rated = park(rated.withColumn("by_host", F.when(blocked, "block").otherwise("allow")), "rated")
    return parts.join(rated, "host", "left").select("page_id", "host", "path", "rule", F.coalesce("told", "by_host", F.lit("allow")).alias("verdict"), F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"))
