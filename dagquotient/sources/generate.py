"""Generators: random and dense DAGs and trees from plain arithmetic, so that SQL can make the same ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagquotient.operators.graph import LabeledDag

#: Fixed multipliers of the arithmetic.
_A, _B, _C = 1_103_515_245, 12_345, 2_147_483_648


def _mixed(*values):
    """Numbers mixed into 0 .. 2^31 - 1 by two steps of a linear congruence, the products kept within 63 bits."""
    x = F.lit(0).cast("long")
    for v in values:
        x = ((x + v) % _C * _A + _B) % _C
    return F.floor((x * _A + _B) % _C / 2**4).cast("long")


def random_dag(spark: SparkSession, n: int, degree: int = 4, labels: int = 8, seed: int = 0, ids: DataFrame | None = None) -> LabeledDag:
    """``n`` nodes of ``labels`` labels; each but the first draws ``degree`` children of smaller ids (some alike).

    ``ids``: a table of the ids from 0 on (column id), in place of ``n``.
    """
    ids = spark.range(n) if ids is None else ids
    nodes = ids.select(F.col("id").alias("node_id"), F.concat(F.lit("l"), (_mixed(F.lit(seed), F.col("id")) % labels).cast("string")).alias("label"))
    drawn = ids.where("id > 0").select(F.col("id").alias("parent"), F.explode(F.sequence(F.lit(1).cast("long"), F.lit(degree).cast("long"))).alias("k"))
    edges = drawn.select("parent", (_mixed(F.lit(seed + 1), F.col("parent"), F.col("k")) % F.col("parent")).alias("child")).distinct()
    return LabeledDag(nodes, edges)


def dense_dag(spark: SparkSession, n: int, percent: int) -> LabeledDag:
    """``percent`` of all pairs of ``n`` nodes, up to the complete DAG; one task makes the edges of a few parents."""
    nodes = spark.range(n).select(F.col("id").alias("node_id"), F.concat(F.lit("n"), (F.col("id") % 5).cast("string")).alias("label"))
    pairs = spark.range(1, n).select(F.col("id").alias("parent"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("id") - 1)).alias("child"))
    return LabeledDag(nodes, pairs.where((F.col("parent") * 7919 + F.col("child") * 104729) % 1000 < 10 * percent))


def dense_groups(rows: DataFrame, percent: int) -> DataFrame:
    """parent, child: ``percent`` of all pairs of ids of each group, for rows of id and part; what ``dense_dag`` takes of one."""
    child = rows.select(F.col("id").alias("child"), "part")
    pairs = rows.select(F.col("id").alias("parent"), "part").join(child, "part").where("child < parent")
    return pairs.where((F.col("parent") * 7919 + F.col("child") * 104729) % 1000 < 10 * percent).select("parent", "child")


def random_tree(spark: SparkSession, n: int, fanout: int = 3, labels: int = 4, seed: int = 0, ids: DataFrame | None = None) -> DataFrame:
    """A tree table in which node i hangs below node (i - 1) / fanout. ``ids``: the ids from 0 to under ``n``, as a table."""
    label = F.concat(F.lit("t"), (_mixed(F.lit(seed), F.col("id")) % labels).cast("string"))
    first = [1]  # the first id of each level but the root's: as many as the tree is deep
    while fanout > 1 and first[-1] < n:
        first.append(first[-1] * fanout + 1)
    depth = F.size(F.filter(F.array(*[F.lit(x).cast("long") for x in first]), lambda x: x <= F.col("id"))) if fanout > 1 else F.col("id").cast("int")
    return (spark.range(n) if ids is None else ids).select(F.col("id").alias("node_id"), F.when(F.col("id") > 0, F.expr(f"(id - 1) div {fanout}")).alias("parent"), depth.alias("depth"), label.alias("label"), F.lit(0).cast("long").alias("doc_id"))
