"""Connected components by alternating star contraction, entirely in joins.

Labels are the smallest identifier reachable. Each round is written to the
shared folder, so a lost executor costs one round at most. A hub with very
many neighbours is aggregated map-side and its join side is split by AQE.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusmap.llm.common import materialize, release


def _both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _lowest(low: DataFrame) -> DataFrame:
    """Written, so that the join does not share the aggregate's exchange and AQE can split a hub's edges."""
    return materialize(low, "lowest")


def _large_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Hang every larger neighbour of a node below the smallest of the node's closed neighbourhood."""
    near = _both_ways(edges)
    low = _lowest(near.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")))
    return (near.filter("b > a").join(low, "a")
            .select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()), low


def _small_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Hang a node and its smaller neighbours below the smallest of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = _lowest(down.groupBy("a").agg(F.min("b").alias("m")))
    moved = down.join(low, "a").filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(low.select("a", F.col("m").alias("b"))).distinct(), low


def _settled(edges: DataFrame) -> bool:
    """True if every node hangs below one node at most, and none of those hangs below another."""
    ends = edges.select(F.col("a").alias("id"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(edges.select(F.col("b").alias("id"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    found = ends.groupBy("id").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return found.filter("up + down > 1").isEmpty()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(a long, b long)`` -> ``(id long, component long)`` for every identifier that has an edge to another.

    Self-loops, nulls and repeated edges are ignored; no edges give an empty
    result. Raises if ``max_rounds`` pass without a fixed point.
    """
    now = materialize(edges.select("a", "b").filter("a <> b")
                      .select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    for _ in range(max_rounds):
        if _settled(now):
            break
        wide, one = _large_star(now)
        narrow, two = _small_star(wide)
        before, now = now, materialize(narrow, "edges")
        release(before, one, two)  # the new table holds all that goes on
    else:
        raise RuntimeError("components did not settle")
    tops = now.select(F.col("b").alias("id")).distinct().select("id", F.col("id").alias("component"))
    return now.select(F.col("a").alias("id"), F.col("b").alias("component")).union(tops)
