"""URL filter: rules first, then trust and distrust propagated over the graph of hosts.

Trust starts at the hosts that the rules allow and follows the links (personalised PageRank);
distrust starts at the hosts that they block and runs against the links, so a host that links to
blocked ones becomes suspect. A host is blocked when its distrust is above `threshold` of the sum of
both; a host that neither reaches is allowed. Only DataFrame functions are used.

What a host without moves onward holds goes back to the seeds, in proportion, so each kind keeps a sum of 1. Rounds end when
no host's score changes by more than `tolerance`, or after `rounds` of them (0.85^48 leaves 0.04 % unsettled).

A null url, or one without "://", has an empty host and path. A null html has no links. Repeated rows are judged each, and a
repeated page_id changes nothing. Links of a host to itself carry nothing. Very long pages are read whole. An empty table
gives no rows; columns other than page_id, url and html are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

RULES = (
    ("com/", "allow"),
    ("example.com/en/", "block"),
    ("www.example.com/en/", "allow"),
    ("net/es/", "block"),
    ("net/fr/", "block"),
)
ROUNDS, TOLERANCE = 48, 1e-12
BROADCAST_HOSTS, SALTS = 1_000_000, 16
_CAPITALS, _SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LINK = r"""(?i)\b(?:href|src)\s*=\s*["']?\s*(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'\s<>]+)"""


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def host_of(url: Column) -> Column:
    """Host with A-Z in lower case: between the first :// and /, ?, # or the end; else empty."""
    return F.coalesce(F.translate(F.regexp_extract(_after_scheme(url), "^[^/?#]*", 0), _CAPITALS, _SMALL), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_after_scheme(url), "^[^/?#]*([^?#]*)", 1), F.lit(""))


def longest_rule(host: Column, path: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else nulls."""
    found = F.struct(F.lit(None).cast("string").alias("rule"), F.lit(None).cast("string").alias("verdict"))
    for rule, verdict in sorted(rules, key=lambda r: (len(r[0]), r[0])):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        found = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def host_links(pages: DataFrame) -> DataFrame:
    """src, dst, links: how often pages of one host link to another."""
    return (
        pages.select(host_of(F.col("url")).alias("src"), F.explode(F.regexp_extract_all(F.col("html"), F.lit(LINK), F.lit(1))).alias("target"))
        .select("src", F.translate("target", _CAPITALS, _SMALL).alias("dst"))
        .where((F.col("src") != "") & (F.col("dst") != "") & (F.col("src") != F.col("dst")))
        .groupBy("src", "dst").agg(F.count("*").alias("links"))
    )


def propagate(edges: DataFrame, seeds: DataFrame, damping: float = 0.85, rounds: int = ROUNDS, tolerance: float = TOLERANCE) -> DataFrame:
    """host, kind, score of personalised PageRank from seeds(host, kind, seed), along edges for kind `trust` and
    against them for kind `distrust`; the seeds of each kind sum to 1. Both kinds go through one join a round."""
    moves = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit("trust").alias("kind"), "links").unionByName(
        edges.select(F.col("dst").alias("a"), F.col("src").alias("b"), F.lit("distrust").alias("kind"), "links")
    )
    outgoing = moves.groupBy("a", "kind").agg(F.sum("links").alias("total"))
    moves = C.materialize(moves.join(outgoing, ["a", "kind"]).select("a", "b", "kind", (F.col("links") / F.col("total")).alias("share")), "url-moves")
    score = seeds.select("host", "kind", F.col("seed").alias("score"))
    if moves.isEmpty():
        return score  # all of it returns to the seeds in every round
    for i in range(rounds):
        sent = moves.join(score, (moves.a == score.host) & (moves.kind == score.kind)).select(F.col("b").alias("host"), moves.kind.alias("kind"), (F.col("share") * F.col("score") * damping).alias("score"))
        passed = sent.groupBy("host", "kind").agg(F.sum("score").alias("score"))
        if i % 4 == 1:  # a round's scores are read twice, so lineage must stay short
            passed = C.materialize(passed, "url-passed")
        # the seeds get what was not passed on: the share (1 - damping), and all that hosts without moves held
        rest = passed.groupBy("kind").agg(F.sum("score").alias("moved"))
        base = seeds.join(F.broadcast(rest), "kind", "left").select("host", "kind", (F.col("seed") * (1 - F.coalesce("moved", F.lit(0.0)))).alias("score"))
        fresh = passed.unionByName(base).groupBy("host", "kind").agg(F.sum("score").alias("score"))
        if i % 4 == 3:
            fresh = C.materialize(fresh, "url-score")
            old = score.withColumnRenamed("score", "old")
            if fresh.join(old, ["host", "kind"], "left").where(F.abs(F.col("score") - F.coalesce("old", F.lit(0.0))) > tolerance).isEmpty():
                return fresh
        score = fresh
    return score


def judge(pages: DataFrame, rules=RULES, damping: float = 0.85, rounds: int = ROUNDS, threshold: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, trust, distrust of every row of pages."""
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    ruled = pages.select("page_id", host.alias("host"), path.alias("path")).withColumn("by_rule", longest_rule(F.col("host"), F.col("path"), rules))
    marks = (
        ruled.where("host != '' and by_rule.verdict is not null")
        .groupBy("host", F.when(F.col("by_rule.verdict") == "allow", "trust").otherwise("distrust").alias("kind"))
        .agg(F.count("*").alias("n"))
    )
    sums = marks.groupBy("kind").agg(F.sum("n").alias("all"))  # two rows at most
    seeds = C.materialize(marks.join(F.broadcast(sums), "kind").select("host", "kind", (F.col("n") / F.col("all")).alias("seed")), "url-seeds")
    score = propagate(C.materialize(host_links(pages), "url-links"), seeds, damping, rounds)
    hosts = score.groupBy("host").agg(
        F.sum(F.when(F.col("kind") == "trust", F.col("score"))).alias("trust"),
        F.sum(F.when(F.col("kind") == "distrust", F.col("score"))).alias("distrust"),
    )
    hosts = C.materialize(hosts, "url-hosts")
    if hosts.count() <= BROADCAST_HOSTS:
        hosts = F.broadcast(hosts)
    else:  # the pages of one host are spread over SALTS keys
        hosts = hosts.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        ruled = ruled.withColumn("salt", F.pmod(F.xxhash64("page_id", "path"), F.lit(SALTS)).cast("int"))
    trust, distrust = F.coalesce("trust", F.lit(0.0)), F.coalesce("distrust", F.lit(0.0))
    by_graph = F.when(distrust > threshold * (trust + distrust), "block").otherwise("allow")
    return ruled.join(hosts, ["host"] + ["salt"] * ("salt" in ruled.columns), "left").select(
        "page_id", "host", "path", F.col("by_rule.rule").alias("rule"), F.coalesce(F.col("by_rule.verdict"), by_graph).alias("verdict"), trust.alias("trust"), distrust.alias("distrust")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(C.table(spark, sf_dir, "pages"))
