"""Connected components of an edge table by alternating large-star and small-star steps, staged round by round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch


def components(edges: DataFrame, scratch: Scratch, name: str = "star") -> DataFrame:
    """node, root (the component's least node) from edges (a, b) of numbers; nodes without a link to another are absent.

    Each round joins nothing and keeps one row per link at most: a node's links are grouped by a map-side minimum, and
    its star is rebuilt by joining that minimum back, so a hub is a skewed join that Spark can split.
    """

    def star(links: DataFrame, large: bool) -> DataFrame:
        # Large star: each larger neighbour is linked to the least of the node and its neighbours; small star: each
        # neighbour that is not larger, and the node itself.
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        joined = both.join(least, "a")
        if large:
            out = joined.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        else:
            out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        return out.where("a <> b").distinct()

    links = scratch.stage(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"{name}0")
    last, turn = None, 0
    while True:
        turn += 1
        done = scratch.stage(star(star(links, True), False), f"{name}{turn}")
        scratch.drop(f"{name}{turn - 1}")
        state = done.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(state) == last:
            return done.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(done.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
        links, last = done, tuple(state)
