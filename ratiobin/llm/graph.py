"""Connected components by alternating star contraction, all in DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ratiobin.llm.common import SPREAD, join_dealt, saved, unsave

#: Edges up to which the least neighbours are broadcast: two nodes an edge at most, rows of 24 bytes, so 24 MB.
BROADCAST_EDGES = 500_000


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
    return row["n"], row["h"]


def _with_least(edges: DataFrame, few: bool) -> DataFrame:
    """(u, v) edges plus m, the least v of each u; the edges of a hub are not gathered in one task."""
    if few:
        return edges.join(F.broadcast(edges.groupBy("u").agg(F.min("v").alias("m"))), "u")
    lanes = edges.withColumn("_lane", F.pmod(F.xxhash64("v"), F.lit(SPREAD)).cast("int")).groupBy("u", "_lane").agg(F.min("v").alias("m"))
    return join_dealt(edges, lanes.groupBy("u").agg(F.min("m").alias("m")), "u", "v")


def connected_components(edges: DataFrame, broadcast_edges: int = BROADCAST_EDGES) -> DataFrame:
    """(src, dst) long edges to (node, component): component is the smallest node that links reach.

    Each round hangs every node's larger neighbours, then its smaller ones, on the smallest node it knows of; rounds
    grow with the logarithm of the longest path.  A round's number of edges is known, and with few the least neighbours are
    broadcast, which saves most of its shuffles.  Nodes without an edge to another node don't appear.  Rounds are
    written to the shared folder, so a lost executor repeats one round at most.
    """
    pair = edges.where("src <> dst").select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v"))
    now = saved(pair.distinct(), "edges")
    mark = _fingerprint(now)
    while mark[0]:
        few = mark[0] <= broadcast_edges
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both, few).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v")).distinct()
        small = _with_least(large, few)
        hung = small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        root = large.groupBy("u").agg(F.min("v").alias("m"))
        after = saved(hung.unionByName(root.select("u", F.col("m").alias("v"))).distinct(), "edges")
        new_mark = _fingerprint(after)
        unsave(now)
        now = after
        if new_mark == mark:
            break
        mark = new_mark
    roots = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
