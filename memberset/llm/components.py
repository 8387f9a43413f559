"""Connected components over an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stage


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _both_ways(edges: DataFrame) -> DataFrame:
    return edges.select(
        F.explode(F.array(F.struct(F.col("u").alias("a"), F.col("v").alias("b")), F.struct(F.col("v").alias("a"), F.col("u").alias("b")))).alias("e")
    ).select("e.a", "e.b")


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(u, v) undirected edges -> (node, root): root is the smallest node of its component.

    Rounds of large-star (hang all larger neighbours on the smallest) and small-star (hang all
    smaller neighbours on the smallest), until nothing changes: O(log n) rounds in practice.
    The minimum of a node is a partial aggregate and is joined back, so that the neighbours of a
    hub are never gathered in one task and a skewed join can split them. Every round is written
    to the shared folder. Self loops and repeated edges are ignored; an empty input gives no rows.
    """
    u_less = F.col("u") < F.col("v")
    edges = edges.where(F.col("u") != F.col("v")).select(
        F.when(u_less, F.col("u")).otherwise(F.col("v")).alias("u"), F.when(u_less, F.col("v")).otherwise(F.col("u")).alias("v")
    )
    edges = stage(edges.distinct(), "edges")
    before = _signature(edges)
    if not before[0]:
        return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(max_rounds):
        pairs = _both_ways(edges)
        low = pairs.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = pairs.where("b > a").join(low, "a").select(F.col("m").alias("u"), F.col("b").alias("v"))
        large = stage(large.where("u <> v").distinct(), "large")
        low = large.groupBy(F.col("v").alias("a")).agg(F.min("u").alias("m"))
        small = large.withColumnRenamed("v", "a").join(low, "a").select(
            F.explode(F.array(F.struct(F.col("m").alias("u"), F.col("u").alias("v")), F.struct(F.col("m").alias("u"), F.col("a").alias("v")))).alias("e")
        ).select("e.u", "e.v")
        edges = stage(small.where("u <> v").distinct(), "edges")
        after = _signature(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select("u").distinct()
    return edges.select(F.col("v").alias("node"), F.col("u").alias("root")).union(roots.select(F.col("u").alias("node"), F.col("u").alias("root")))
