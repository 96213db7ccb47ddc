"""Connected components of an edge table by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def _least(pairs: DataFrame) -> DataFrame:
    """(v, m): the smallest of v and its neighbours in ``pairs(v, u)``."""
    return pairs.groupBy("v").agg(F.least(F.min("u"), F.first("v")).alias("m"))


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(id, component) for every id in ``edges(a, b)``: the smallest id reachable.

    Both steps aggregate before they join, so a vertex with very many edges costs one
    partial row per task; each round is written to the shared folder.
    """
    now = materialise(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc")
    seen = None
    for _ in range(most_rounds):
        both = now.select(F.col("a").alias("v"), F.col("b").alias("u")).union(now.select(F.col("b").alias("v"), F.col("a").alias("u")))
        large = both.join(_least(both), "v").where("u > v").select(F.col("m").alias("a"), F.col("u").alias("b")).where("a <> b").distinct()
        down = large.select(F.col("b").alias("v"), F.col("a").alias("u"))
        least = _least(down)
        small = down.join(least, "v").select(F.col("m").alias("a"), F.col("u").alias("b")).union(least.select(F.col("m").alias("a"), F.col("v").alias("b"))).where("a <> b").distinct()
        now = materialise(small, "cc")
        state = now.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first()
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    # now every edge leads from the smallest id of its component
    return now.select(F.col("b").alias("id"), F.col("a").alias("component")).union(now.select(F.col("a").alias("id"), F.col("a").alias("component"))).distinct()
