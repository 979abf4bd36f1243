"""Positions in sorted order as new node ids, and edges rewritten to them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.functions.lineage import cut, small
from dagquotient.operators.graph import LabeledDag


def sorted_numbering(df: DataFrame, order: list[str], out: str = "new_id") -> DataFrame:
    """``df`` with the 1-based position of each row in the given order, which must be total.

    Rows are dealt to ranges and numbered there; counts of the ranges before are added. No task sees all rows.
    """
    dealt = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_p", F.spark_partition_id())
    dealt = cut(dealt)  # ranges come from samples: they are fixed before they are counted
    counts = dealt.groupBy("_p").agg(F.count("*").alias("n"))
    before = counts.select("_p", (F.sum("n").over(Window.orderBy("_p")) - F.col("n")).alias("before"))  # a row for each range
    local = F.row_number().over(Window.partitionBy("_p").orderBy(*order))
    return dealt.join(F.broadcast(before), "_p").withColumn(out, (F.col("before") + local).cast("long")).drop("_p", "before")


def relabel(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """parent, child by new ids: two joins, and sorted by child within ranges of it."""
    n = ids.count()
    child = small(ids.select(F.col("node_id").alias("child"), F.col("new_id").alias("c")), n)
    parent = small(ids.select(F.col("node_id").alias("parent"), F.col("new_id").alias("p")), n)
    out = edges.join(child, "child").join(parent, "parent").select(F.col("p").alias("parent"), F.col("c").alias("child"))
    return out.repartitionByRange("child").sortWithinPartitions("child", "parent")


def renumbered(g: LabeledDag, ranked: DataFrame, keys: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """new_id, node_id, rank, label, hash and the edges by new ids: larger ranks have larger ids."""
    nodes = cut(sorted_numbering(ranked, [*(keys or ["rank", "label"]), "node_id"]))
    return nodes, relabel(g.edges, nodes)


def check_numbering(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """parent, child of edges whose child is not numbered below its parent: no row if all is well."""
    return edges.where("child >= parent").select("parent", "child")


def topological_ids(g: LabeledDag, ranked: DataFrame) -> tuple[LabeledDag, DataFrame]:
    """The graph with ids that put children before parents, and node_id, new_id."""
    ids = cut(sorted_numbering(ranked.select("node_id", "rank", "label"), ["rank", "node_id"]))
    return LabeledDag(ids.select(F.col("new_id").alias("node_id"), "label"), relabel(g.edges, ids)), ids.select("node_id", "new_id")
