"""Connected components of a distributed edge list, by alternating star contractions.

Loops and repeated edges don't matter; without edges the result is empty.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import cut, drop, told


def _least(edges: DataFrame) -> DataFrame:
    """u, m: the least of u and its neighbours. A hub is one row of it, so a join can split its edges."""
    return edges.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))


def _sums() -> dict[str, Column]:
    """What tells edge lists of one length apart: two sums over hashes of their rows."""
    return {"x": F.bit_xor(F.xxhash64("u", "v")), "y": F.sum(F.shiftright(F.xxhash64("v", "u"), 24))}


def _alike(edges: DataFrame, other: DataFrame) -> bool:
    return all(told(edges, name) == told(other, name) for name in ("rows", "x", "y"))


def components(edges: DataFrame) -> DataFrame:
    """node, root: for every node of ``edges`` (a, b: longs) the least node that it is connected with."""
    edges = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), **_sums())
    done = told(edges) == 0
    while not done:
        # to every larger neighbour, the least of the neighbourhood
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = cut(both.join(_least(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        # among what is smaller, everything to the least
        pairs = large.join(_least(large), "u")
        new = cut(pairs.select(F.col("v").alias("u"), F.col("m").alias("v")).union(pairs.select("u", F.col("m").alias("v"))).where("u <> v").distinct(), **_sums())
        done = _alike(edges, new)
        drop(large, edges)
        edges = new
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
