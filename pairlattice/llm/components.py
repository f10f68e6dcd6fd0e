"""Connected components of a link table by alternating large and small stars; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import Workspace


def _large(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min(F.least("a", "b")).alias("m"))
    return both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").where(F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def components(edges: DataFrame, space: Workspace, rounds: int = 60) -> DataFrame:
    """(node, label): the least node of its component for every node with a link; ``edges`` has columns a, b.

    Each round sends a node its least neighbour, combined before the shuffle; a star's centre may be
    any share of all links, its rows are split by the joins' skew handling.  The number of rounds grows
    with the square of the logarithm of the longest chain; an error tells if ``rounds`` are not enough.
    """
    now = space.keep(edges.where("a <> b").select("a", "b").distinct())
    before = None
    for _ in range(rounds):
        now = space.keep(_small(_large(now)))
        seen = now.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b") % 1_000_000_007), F.lit(0))).first()
        if seen == before or seen[0] == 0:
            break
        before = seen
    else:
        raise RuntimeError(f"components are not settled after {rounds} rounds")
    return space.keep(now.select(F.col("a").alias("node"), F.col("b").alias("label")).union(now.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct()))
