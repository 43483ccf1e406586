"""Connected components of an edge table by alternating star contractions.

Each round joins every node with its smallest neighbour: first larger neighbours are
tied to it, then smaller ones. Chains halve per round, so rounds grow with the log
of the longest path. Rounds are written to the shared folder, which cuts lineage; all
steps are aggregations with map-side combine or joins on node ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulecredit.llm.runtime import SharedStore


def _large_star(edges: DataFrame) -> DataFrame:
    """edges (u > v): ties each larger neighbour of a node to the node's smallest."""
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """edges (u > v): ties each smaller neighbour of a node, and the node, to the smallest."""
    low = edges.groupBy("u").agg(F.min("v").alias("m"))
    tied = edges.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v")
    return tied.unionByName(low.select("u", F.col("m").alias("v"))).distinct()


def connected_components(edges: DataFrame, store: SharedStore, name: str = "cc") -> DataFrame:
    """(node, component) for every node of ``edges`` (a, b); component is the smallest node id.

    Loops and null ends are ignored, repeated edges count once; no edges give no rows.
    """
    links = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    links = store.write(links, f"{name}-0")
    seen, k = None, 0
    while True:
        k += 1
        links = store.write(_small_star(_large_star(links)), f"{name}-{k}")
        store.drop(f"{name}-{k - 1}")
        row = links.agg(F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 31))).alias("h")).first()
        state = (row["n"], row["h"])
        if state == seen:
            break
        seen = state
    roots = links.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return links.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
