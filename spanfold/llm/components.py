"""Connected components of an edge table by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import written


def _star(edges: DataFrame, large: bool) -> DataFrame:
    both = edges if not large else edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m"))
    met = both.join(least, "u")
    if large:  # every larger neighbour of u hangs under u's smallest neighbour
        out = met.where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
    else:  # edges point down: every smaller neighbour, and u itself, hang under the smallest
        out = met.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.where("u > v").distinct()


def components(edges: DataFrame) -> DataFrame:
    """edges (u, v) of comparable keys, to (node, root): root is the smallest key reachable.

    Nodes without an edge are left out. Rounds are written tables, so a lost executor costs one
    round; a round only aggregates and joins on node keys, and the driver sees two numbers of it.
    """
    edges = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct()
    edges = written(edges, "edges")
    seen = None
    while True:
        mark = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(mark) == seen:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = tuple(mark)
        edges = written(_star(_star(edges, large=True), large=False), "edges")
