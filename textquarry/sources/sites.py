"""Site discovery and verification: candidate lists, reject rules, votes, outcomes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BAD_WORDS = ("pill", "casino", "bets", "adult")
ORIGINS = ("search", "volunteer", "crawl", "government")


def candidate_sites(lists: dict[str, DataFrame]) -> DataFrame:
    """Union of host lists; each host once, with the sorted origins that named it."""
    rows = None
    for origin, df in lists.items():
        part = df.select("host", F.lit(origin).alias("origin")).distinct()
        rows = part if rows is None else rows.unionByName(part)
    return rows.groupBy("host").agg(F.array_join(F.array_sort(F.collect_set("origin")), ",").alias("origins"))


def top_hosts(pages: DataFrame, k: int) -> DataFrame:
    """Hosts of most extracted text: rows host, text."""
    return pages.groupBy("host").agg(F.sum(F.length("text")).alias("chars"), F.count(F.lit(1)).alias("pages")).orderBy(F.col("chars").desc(), "host").limit(k)


def reasons(is_target: Column, host: Column, translated: Column, active: Column) -> Column:
    """Every rule that rejects; any one is enough."""
    bad = F.lit(False)
    for w in BAD_WORDS:
        bad = bad | host.contains(w)
    return F.array_compact(F.array(F.when(~is_target, "language"), F.when(bad, "adult_or_gambling"), F.when(translated, "machine_translated"), F.when(~active, "inactive")))


def decide(votes: DataFrame, key: str, vote: str, min_votes: int, quorum: float) -> DataFrame:
    out = votes.groupBy(key).agg(F.count(F.lit(1)).alias("votes"), F.sum(vote).cast("long").alias("yes"))
    return out.withColumn("decision", F.when(F.col("votes") < min_votes, "open").when(F.col("yes") >= F.col("votes") * F.lit(quorum), "accept").otherwise("reject"))
