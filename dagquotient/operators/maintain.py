"""Partitions that follow a growing or changing graph, without grouping all of it again.

A node is told by its label and its children's blocks, so nodes that keep all their descendants keep their equals. What
is added, or lies above a changed edge, is decided rank by rank against a dictionary of the blocks that stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagquotient.functions.lineage import cut, fresh_path, small
from dagquotient.operators import ranks
from dagquotient.operators.graph import LabeledDag
from dagquotient.operators.partition import _named, families, forward_partition


def dictionary(g: LabeledDag, partition: DataFrame) -> DataFrame:
    """block_id, label, family: what tells each block, taken from its smallest node."""
    models = cut(partition.groupBy("block_id").agg(F.min("node_id").alias("node_id")))
    few = small(models.select("node_id"), models.count())
    part = LabeledDag(g.nodes.join(few, "node_id", "left_semi"), g.edges.join(few.withColumnRenamed("node_id", "parent"), "parent", "left_semi"))
    return part.nodes.join(families(part, partition), "node_id").join(models, "node_id").select("block_id", "label", "family")


def append_nodes(g: LabeledDag, partition: DataFrame, new_nodes: DataFrame, new_edges: DataFrame) -> DataFrame:
    """node_id, block_id of the graph with ``new_nodes`` and ``new_edges``, whose parents must be new.

    Blocks of ``g`` keep their names and nodes; a block that no old node belongs to is named by its smallest one.
    """
    spark = g.nodes.sparkSession
    added = LabeledDag.of(new_nodes, new_edges).cut()
    inner = LabeledDag(added.nodes, added.edges.join(added.nodes.select(F.col("node_id").alias("child")), "child", "left_semi"))
    ranked = cut(ranks.by_peeling(inner).select("node_id", "rank", "label"))
    top = ranked.agg(F.max("rank")).first()[0]
    if top is None:
        return partition
    known, blocks = fresh_path(spark, "dictionary"), fresh_path(spark, "appended")
    dictionary(g, partition).write.parquet(known)
    touched = cut(partition.join(added.edges.select(F.col("child").alias("node_id")).distinct(), "node_id", "left_semi"))
    for r in range(top + 1):
        here = ranked.where(F.col("rank") == r)
        below = touched if r == 0 else touched.union(spark.read.schema(touched.schema).parquet(blocks))
        edges = added.edges.join(here.select(F.col("node_id").alias("parent")), "parent", "left_semi")
        told = cut(here.select("node_id", "label").join(families(LabeledDag(here, edges), below), "node_id"))
        told_before = spark.read.schema("block_id long, label string, family array<long>").parquet(known)
        kinds = told.groupBy("label", "family").agg(F.min("node_id").alias("least"))
        met = kinds.join(told_before, kinds["label"].eqNullSafe(told_before["label"]) & (kinds["family"] == told_before["family"]), "left")
        met = cut(met.select(kinds["label"], kinds["family"], F.coalesce("block_id", "least").alias("block_id"), F.col("block_id").isNull().alias("unseen")))
        out = told.join(small(met, met.count()), told["label"].eqNullSafe(met["label"]) & (told["family"] == met["family"]))
        out.select("node_id", "block_id").write.mode("append").parquet(blocks)
        met.where("unseen").select("block_id", "label", "family").write.mode("append").parquet(known)
    return partition.select("node_id", "block_id").union(spark.read.schema("node_id long, block_id long").parquet(blocks))


def ancestors(g: LabeledDag, start: DataFrame) -> DataFrame:
    """node_id of ``start`` and of all that reach it; a round for each step up, over the edges of the last one."""
    spark, at = g.nodes.sparkSession, fresh_path(g.nodes.sparkSession, "cone")
    front = cut(start.select("node_id").distinct())
    seen = front
    while not front.isEmpty():
        front.write.mode("append").parquet(at)
        seen = spark.read.schema(front.schema).parquet(at)
        up = g.edges.join(front.withColumnRenamed("node_id", "child"), "child", "left_semi").select(F.col("parent").alias("node_id")).distinct()
        front = cut(up.join(seen, "node_id", "left_anti"))
    return seen


def changed(g: LabeledDag, inserted: DataFrame, deleted: DataFrame) -> LabeledDag:
    """``g`` without the edges ``deleted`` and with those ``inserted`` (parent, child); an edge in both stays."""
    kept = g.edges.join(deleted.select("parent", "child"), ["parent", "child"], "left_anti")
    return LabeledDag(g.nodes, kept.unionByName(inserted.select("parent", "child")).distinct())


def edge_changes(g: LabeledDag, partition: DataFrame, inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """node_id, block_id of the changed graph, named by smallest nodes; it must still have no cycle.

    All that reaches a changed edge is decided anew, as nodes added to the rest, which has lost no descendant.
    """
    after = changed(g, inserted, deleted).cut()
    starts = inserted.select(F.col("parent").alias("node_id")).union(deleted.select(F.col("parent").alias("node_id")))
    cone = cut(ancestors(after, starts))
    few = small(cone, cone.count())
    above = few.withColumnRenamed("node_id", "parent")
    rest = LabeledDag(after.nodes.join(few, "node_id", "left_anti"), after.edges.join(above, "parent", "left_anti")).cut()
    kept = cut(_named(cut(partition.join(few, "node_id", "left_anti").withColumnRenamed("block_id", "before")), ["before"]))
    found = append_nodes(rest, kept, after.nodes.join(few, "node_id", "left_semi"), after.edges.join(above, "parent", "left_semi"))
    return renamed(found)


def renamed(partition: DataFrame) -> DataFrame:
    """Blocks named by their smallest nodes."""
    return _named(cut(partition.withColumnRenamed("block_id", "before")), ["before"])


def recompute(g: LabeledDag, inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """The baseline: the partition of the whole changed graph from the start."""
    return forward_partition(changed(g, inserted, deleted).cut())
