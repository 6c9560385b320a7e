"""Connected components by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace


def _stars(edges: DataFrame) -> DataFrame:
    """One large star and one small star. ``edges``: a > b, distinct."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    # Each edge with its larger end as a: the smaller neighbours of a, and a itself, go to the least of them.
    large = large.where("a <> b").distinct()
    least = large.groupBy("a").agg(F.min("b").alias("m"))
    joined = large.join(least, "a")
    small = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    return small.where("a <> b").distinct()


def connected(links: DataFrame, ws: Workspace, most_rounds: int = 60) -> DataFrame:
    """(v, root) for every vertex of ``links`` (a, b); root is the least vertex of its component.

    Only two numbers a round come to the driver, to see whether the edges still change.
    """
    edges = ws.save(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = None
    for _ in range(most_rounds):
        told = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(told) == seen or not told[0]:
            break
        seen = tuple(told)
        edges, old = ws.save(_stars(edges), "edges"), edges
        ws.drop(old)
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("a").alias("v"), F.col("b").alias("root"))
