"""URL filter by rules and, where no rule fits, by trust and distrust spread over host links.

Native: DataFrame functions only. Trust is a personalised PageRank over host edges from hosts that rules
allow; distrust is the same over the reversed edges from hosts that rules block. Mass of hosts without
outgoing edges returns to the seeds. The ranks are spread until their change, summed over all hosts, is at most
SETTLED, which a share of 1 - DAMPING brings about after a number of rounds that no data can raise. Scores are taken back to pages (seed pages reached, per page of the
host); a host is blocked when its distrust exceeds its trust by more than THRESHOLD.

Edge cases: a null url, or one without `://`, has empty host and path, fits no rule and is allowed; null
html has no links; links within a host are not edges; repeated pages count repeatedly; without seeds or
edges the scores are the hosts' own shares of blocked and allowed pages.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from pacedfl.llm.common import checkpointed, dealt, repeated, salted

# Fixed values of the result contract: (verdict, rule).
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
DAMPING = 0.85
SETTLED = 1e-4
LOOK_EVERY = 4  # rounds between two looks at the change
THRESHOLD = 0.5
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LINK = r"""(?i)<a\s[^>]*?href\s*=\s*["']?((?:https?:)?//[^"'\s>]+)"""


def host_of(url: Column) -> Column:
    """After the first `://` up to `/`, `?`, `#` or the end; A-Z in lower case; empty without one."""
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"://([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"://[^/?#]*([^?#]*)", 1)


def split_rule(rule: str) -> tuple[str, str]:
    host, _, path = rule.partition("/")
    return host, f"/{path}"


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, or null. The list is a parameter, not data: it becomes one CASE."""

    def fits(rule: str) -> Column:
        h, p = split_rule(rule)
        return ((host == h) | F.endswith(host, F.lit(f".{h}"))) & F.startswith(path, F.lit(p))

    ordered = sorted((r for _, r in rules), key=lambda r: (-len(r), r))
    return F.coalesce(*(F.when(fits(r), F.lit(r)) for r in ordered), F.lit(None).cast("string"))


def host_edges(pages: DataFrame) -> DataFrame:
    """(source, target, n) for links between different hosts; counted in each task before the shuffle."""
    links = pages.select(host_of(F.col("url")).alias("source"), F.explode(F.regexp_extract_all(F.col("html"), F.lit(LINK), F.lit(1))).alias("link"))
    target = host_of(F.when(F.startswith("link", F.lit("//")), F.concat(F.lit("http:"), "link")).otherwise(F.col("link")))
    return links.select("source", target.alias("target")).where("source <> '' and target <> '' and source <> target").groupBy("source", "target").agg(F.count("*").alias("n"))


def most_rounds(settled: float = SETTLED, damping: float = DAMPING) -> int:
    """After so many rounds the change is at most settled: it begins at 2 at most and shrinks by damping each time."""
    return math.ceil(math.log(settled / 2) / math.log(damping)) + 1


def propagate(seeds: DataFrame, edges: DataFrame, settled: float = SETTLED, damping: float = DAMPING) -> DataFrame:
    """Personalised PageRank of (kind, host) from seeds (kind, host, seed) over edges (kind, source, target, n).

    seed sums to 1 within a kind. A host with a large share of the edges is dealt over tasks by target.
    """
    out = edges.groupBy("kind", "source").agg(F.sum("n").alias("out"), F.count("*").alias("n"))
    nodes = seeds.select("kind", "host").union(edges.select("kind", "source")).union(edges.select("kind", "target")).distinct()
    nodes = nodes.join(seeds, ["kind", "host"], "left").join(out.select("kind", F.col("source").alias("host"), F.lit(False).alias("ends")), ["kind", "host"], "left")
    nodes = checkpointed(nodes.select("kind", "host", F.coalesce("seed", F.lit(0.0)).alias("seed"), F.coalesce("ends", F.lit(True)).alias("ends")))
    hot = checkpointed(dealt(out.groupBy("source").agg(F.max("n").alias("n")), "source", edges.count()))
    shares = salted(edges.join(out.select("kind", "source", "out"), ["kind", "source"]), hot, "source", F.col("target"))
    shares = checkpointed(shares.select("kind", "source", "target", "__salt", (F.col("n") / F.col("out")).alias("share")))
    rank = nodes.withColumn("rank", F.col("seed"))
    for t in range(most_rounds(settled, damping)):
        given = repeated(rank.select("kind", F.col("host").alias("source"), "rank"), hot, "source")
        got = shares.join(given, ["kind", "source", "__salt"]).groupBy("kind", F.col("target").alias("host")).agg(F.sum(F.col("rank") * F.col("share")).alias("got"))
        ended = rank.groupBy("kind").agg(F.sum(F.when(F.col("ends"), F.col("rank")).otherwise(0.0)).alias("back"))
        new = (1 - damping) * F.col("seed") + damping * (F.coalesce("got", F.lit(0.0)) + F.col("back") * F.col("seed"))
        both = rank.join(got, ["kind", "host"], "left").join(F.broadcast(ended), "kind")
        both = checkpointed(both.select("kind", "host", "seed", "ends", new.alias("rank"), F.col("rank").alias("old")))
        rank = both.drop("old")
        if t % LOOK_EVERY == LOOK_EVERY - 1 and both.groupBy("kind").agg(F.sum(F.abs(F.col("rank") - F.col("old"))).alias("moved")).where(F.col("moved") > settled).isEmpty():
            break
    return rank.select("kind", "host", "rank")


def judge_urls(pages: DataFrame, rules=RULES, threshold: float = THRESHOLD, settled: float = SETTLED) -> DataFrame:
    """page_id, host, path, rule, verdict and the host's score for every page.

    What is broadcast: two rows of returned mass, and fewer than HOT_SHARE hot hosts.
    """
    verdict_of = reduce(lambda c, r: c.when(F.col("rule") == r[1], r[0]), rules[1:], F.when(F.col("rule") == rules[0][1], rules[0][0]))
    rows = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rows = rows.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules)).withColumn("ruled", verdict_of)
    hosts = rows.where("host <> ''").groupBy("host").agg(F.count("*").alias("pages"), F.count_if(F.col("ruled") == "allow").alias("trust"), F.count_if(F.col("ruled") == "block").alias("distrust"))
    hosts = checkpointed(hosts)
    total = hosts.agg(*(F.coalesce(F.sum(k), F.lit(0)).alias(k) for k in ("trust", "distrust"))).first()
    links = checkpointed(host_edges(pages))
    seeds = hosts.select("host", F.explode(F.create_map(*(x for k in ("trust", "distrust") for x in (F.lit(k), F.col(k) / F.lit(float(max(total[k], 1))))))).alias("kind", "seed")).where("seed > 0")
    if links.isEmpty():
        rank = seeds.select("kind", "host", F.col("seed").alias("rank"))  # all mass returns to the seeds
    else:
        edges = links.select(F.lit("trust").alias("kind"), "source", "target", "n").union(links.select(F.lit("distrust"), F.col("target"), F.col("source"), "n"))
        rank = propagate(seeds, edges, settled)
    mass = F.when(F.col("kind") == "trust", -float(total["trust"])).otherwise(float(total["distrust"])) * F.col("rank")
    score = rank.groupBy("host").agg(F.sum(mass).alias("mass")).join(hosts, "host").select("host", F.round(F.col("mass") / F.col("pages"), 9).alias("score"))
    judged = hosts.select("host", F.col("pages").alias("n")).join(score, "host", "left").select("host", "n", F.coalesce("score", F.lit(0.0)).alias("host_score"))
    # pages of one host may be a third of all: those of a hot host are dealt over tasks
    hot = checkpointed(dealt(judged, "host", hosts.agg(F.coalesce(F.sum("pages"), F.lit(0))).first()[0]))
    judged = repeated(judged.drop("n"), hot, "host").withColumnsRenamed({"host": "__host", "__salt": "__part"})
    rows = salted(rows, hot, "host", F.struct("page_id", "path"))
    out = rows.join(judged, (rows.host == judged["__host"]) & (rows["__salt"] == judged["__part"]), "left")
    verdict = F.coalesce("ruled", F.when(F.coalesce("host_score", F.lit(0.0)) > threshold, "block").otherwise("allow"))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), F.coalesce("host_score", F.lit(0.0)).alias("host_score"))
