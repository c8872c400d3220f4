"""Connected components of a table of links, by alternating large and small stars; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import Workspace


def _large(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small(edges: DataFrame) -> DataFrame:
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    joined = edges.join(least, "a")
    return joined.select(F.inline(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b"))))).where("a <> b").distinct()


def components(edges: DataFrame, space: Workspace, name: str) -> DataFrame:
    """(node, component) for each node of ``edges`` (a, b); the component is its smallest node.

    Each round halves the depth of a chain at least, so rounds grow with the logarithm of the longest path. Links of a node with itself
    and repeated links do nothing; an empty table has no components; null ends are dropped.
    """
    ends = [F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")]
    now = space.store(edges.where("a <> b").select(*ends).distinct(), f"{name}0")
    state, k = None, 0
    while True:
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()
        if seen == state or not seen[0]:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(now.select("b", "b")).distinct()
        state, k = seen, k + 1
        now = space.store(_small(_large(now)), f"{name}{k}")
        if k > 1:
            space.drop(f"{name}{k - 2}")
