"""Connected components of an edge table without collecting links: alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import settle


def _stars(pairs: DataFrame) -> DataFrame:
    """(u, v) -> (v, smallest of u and its v): partial aggregation first, so a hub costs one row for each task."""
    low = pairs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return pairs.join(low, "u")


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """``edges``(a long, b long, any direction, repeats allowed) -> (node, root), root the smallest reachable node.

    Every round writes its edges to the shared folder.  Nodes without an edge don't occur in the result;
    null ends and self-links are ignored; an empty table gives an empty result.
    """
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    e = settle(e, "edges")
    seen = _digest(e)
    while seen[0]:
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).union(e.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = _stars(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = _stars(large.where("u <> v").distinct())
        e = small.select(F.col("v").alias("a"), F.col("m").alias("b")).union(small.select(F.col("u").alias("a"), F.col("m").alias("b")))
        e = settle(e.where("a <> b").distinct(), "edges")
        now = _digest(e)
        if now == seen:
            break
        seen = now
    roots = e.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots.union(e.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
