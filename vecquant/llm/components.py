"""Connected components of link tables, by alternating star contractions.

Links are rewired toward the smallest node in reach until every node hangs on its component's
smallest one. Each round cuts lineage with a checkpoint in the shared folder, and no node's
links are gathered in one task: smallest neighbours come from partial aggregates, which are
written before they are joined back, so that both sides of a join are plain exchanges and
adaptive execution can split a node that has very many links.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.llm.common import cut_lineage


def smallest_reachable(links: DataFrame, rounds: int = 60) -> DataFrame:
    """node, component for every node with a link to another one; links: a, b of type long.

    Loops, repeated links and nulls are ignored. Nodes without links have no row.
    """
    edges = links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    edges = cut_lineage(edges.distinct())
    mark = _mark(edges)
    for _ in range(rounds):
        if not mark[0]:
            break
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = cut_lineage(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
        large = edges.select(F.col("v").alias("u"), F.col("u").alias("w")).join(low, "u").select(F.col("w").alias("u"), F.col("m").alias("v"))
        # Keep each node's own tie to its smallest neighbour, so that nothing comes apart.
        large = cut_lineage(large.union(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct())
        least = cut_lineage(large.groupBy("u").agg(F.min("v").alias("m")))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.union(least.select("u", F.col("m").alias("v")))
        small = small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v")
        edges = cut_lineage(small.distinct())
        new = _mark(edges)
        if new == mark:
            break
        mark = new
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = edges.select(F.col("v").alias("node")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        roots.select("node", F.col("node").alias("component"))
    )


def _mark(edges: DataFrame) -> tuple[int, int]:
    """Count and order-free checksum of the links."""
    code = F.xxhash64("u", "v")
    row = edges.agg(F.count("*").alias("n"), F.sum(code.bitwiseAND(F.lit(0xFFFFFFFFFF))).alias("s")).first()
    return row.n, row.s or 0
