"""Connected components by alternating star contractions, all in DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import materialize


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One star step over edges (u, v) with u > v: neighbours of a node go to its smallest one.

    The large step hangs the neighbours above a node below its minimum, the small step those
    beneath it. Minima are aggregated before the join, so a hub sends one row to each partition.
    """
    near = edges.select("u", "v")
    if large:
        near = near.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    lows = near.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    joined = near.join(lows, "u")
    if large:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(
            lows.select("u", F.col("m").alias("v"))
        )
    return out.where("u > v").distinct()


def connected_components(links: DataFrame, left: str, right: str, max_rounds: int = 100) -> DataFrame:
    """``node, root`` for every node of ``links``; the root is the smallest node of its component.

    Each round is written to the shared folder, so lineage stays one round long. The loop ends
    when a round leaves the edge set as it was, which the two star steps reach in logarithmically
    many rounds in practice; nodes without links are not listed.
    """
    edges = links.select(F.greatest(left, right).alias("u"), F.least(left, right).alias("v")).where("u > v").distinct()
    edges = materialize(edges, "edges")
    state = None
    for _ in range(max_rounds):
        edges = materialize(_star(_star(edges, True), False), "edges")
        now = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if state == tuple(now):
            break
        state = tuple(now)
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
