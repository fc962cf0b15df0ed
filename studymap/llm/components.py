"""Connected components of a table of links by alternating star contraction, without a driver-side graph.

Rounds go on until the links no longer change; their number grows with the logarithm of the longest path. While there are at most `MOST_SENT` links, the least neighbours are
broadcast; beyond that they are joined by node and salt, so that a hub of many links is dealt to several tasks.
Links with a null end and links of a node to itself don't count, repeated links count once, and an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import checkpointed, salt, salts_seen, spread


#: Links whose least neighbours (two integers for each node) are sent to all tasks.
MOST_SENT = 100_000


def _with_least(links: DataFrame, least, few: bool) -> DataFrame:
    """Each link beside its first node's least neighbour, `m`."""
    if few:
        return links.join(F.broadcast(links.groupBy("a").agg(least.alias("m"))), "a")
    links = links.withColumn("_salt", salt("b"))
    return links.join(spread(links.groupBy("a").agg(least.alias("m"), salts_seen())), ["a", "_salt"])


def _large_star(links: DataFrame, few: bool) -> DataFrame:
    both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    x = _with_least(both, F.least(F.min("b"), F.col("a")), few).where("b > a")
    return x.select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(links: DataFrame, few: bool) -> DataFrame:
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    x = _with_least(down, F.min("b"), few)
    # A node's link to its least neighbour b = m is the one that stays with the node.
    return x.select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def components(links: DataFrame) -> DataFrame:
    """Links (a, b) -> (node, component), component being the least node reachable; only nodes that have a link to another node appear."""
    edges = checkpointed(links.select("a", "b").where("a <> b").distinct())
    mark = lambda: tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b") % 1_000_000_007)).first())
    now, before = mark(), None
    while now != before:
        few = now[0] <= MOST_SENT
        edges = checkpointed(_small_star(_large_star(edges, few), few))
        now, before = mark(), now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
