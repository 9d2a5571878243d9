"""Connected components by alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for each node with an edge; component is the smallest node reachable.

    Each round writes the edges to the shared folder; the rounds end when a round
    changes nothing. Minima are partially aggregated, so a hub costs no single task.
    Edges with a null end and loops are ignored; repeated edges count once; without
    edges the result is empty.
    """
    edge = materialize(_oriented(edges, a, b), "edges")
    before = None
    while (now := _state(edge)) != before:
        before = now
        if not now[0]:
            break
        both = edge.unionByName(edge.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("m", "u").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        edge = materialize(small.where("u > v").distinct(), "edges")
    roots = edge.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edge.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)


def _oriented(edges: DataFrame, a: str, b: str) -> DataFrame:
    ends = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    return ends.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()


def _state(edge: DataFrame) -> tuple:
    return tuple(edge.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.bit_xor(F.xxhash64("v", "u", F.lit(1)))).first())
