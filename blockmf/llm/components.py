"""Connected components by alternating star contraction, in DataFrame operations only.

Each round replaces edges by links to the smallest neighbour (larger neighbours first, then smaller ones), so a
graph of any diameter becomes a set of stars in a logarithmic number of rounds. Edges stay as many as they were
or fewer; each round is written to the shared folder, so no lineage grows and nothing is collected but two sums.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import cut


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where("v > u and v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Edges come as (u, v) with v < u."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def connected_components(edges: DataFrame, src: str, dst: str, max_rounds: int = 100) -> DataFrame:
    """edges(src, dst) of one ordered type -> (node, component), component = least node id. Nodes without an edge to another node are absent."""
    links = edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).where("u != v").distinct()
    links = cut(links, "cc")
    mark = _mark(links)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        links = cut(_small_star(_large_star(links)), "cc")
        before, mark = mark, _mark(links)
        if mark == before:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = links.select(F.col("v").alias("node")).distinct()
    return links.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots.withColumn("component", F.col("node")))
