"""Index graphs on a partition: the smallest bisimilar graph, extents, path and twig queries, sizes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagquotient.functions.lineage import cut
from dagquotient.operators.graph import LabeledDag, roots


@dataclass(frozen=True)
class BisimIndex:
    """blocks: block_id, label, n_members, has_root. edges: parent_block, child_block. extents: block_id, node_id."""

    blocks: DataFrame
    edges: DataFrame
    extents: DataFrame

    def graph(self) -> LabeledDag:
        return LabeledDag(self.blocks.select(F.col("block_id").alias("node_id"), "label"), self.edges.select(F.col("parent_block").alias("parent"), F.col("child_block").alias("child")))


def build_index(g: LabeledDag, partition: DataFrame) -> BisimIndex:
    """An edge leads from block A to block B if one leads from some member of A to some member of B."""
    top = roots(g).select("node_id", F.lit(True).alias("is_root"))
    rows = partition.join(g.nodes, "node_id").join(top, "node_id", "left")
    blocks = rows.groupBy("block_id").agg(F.min("label").alias("label"), F.count("*").alias("n_members"), F.max(F.coalesce("is_root", F.lit(False))).alias("has_root"))
    parent = partition.select(F.col("node_id").alias("parent"), F.col("block_id").alias("parent_block"))
    child = partition.select(F.col("node_id").alias("child"), F.col("block_id").alias("child_block"))
    edges = g.edges.join(child, "child").join(parent, "parent").select("parent_block", "child_block").distinct()
    return BisimIndex(blocks, edges, partition.select("block_id", "node_id"))


def write_index(index: BisimIndex, path: str, buckets: int = 16) -> None:
    """Extents clustered by block (files of a bucket sorted by it), blocks and edges beside them."""
    index.extents.repartition(buckets, "block_id").sortWithinPartitions("block_id", "node_id").write.parquet(f"{path}/extents")
    index.blocks.write.parquet(f"{path}/blocks")
    index.edges.write.parquet(f"{path}/edges")


def read_index(spark, path: str) -> BisimIndex:
    return BisimIndex(*(spark.read.parquet(f"{path}/{x}") for x in ("blocks", "edges", "extents")))


def _steps(nodes: DataFrame, edges: DataFrame, path: list[str], first: DataFrame) -> DataFrame:
    """Nodes at the end of a path of labels (``*``: any; ``**``: any number of further edges) from those of ``first``."""
    now = first.where((F.col("label") == path[0]) | F.lit(path[0] == "*")).select("id").distinct()
    deep = False
    for label in path[1:]:
        if label == "**":
            deep = True
            continue
        if deep:
            now, deep = _below(edges, now), False
        ends = now.join(edges, F.col("id") == F.col("parent")).select(F.col("child").alias("id")).distinct()
        now = ends.join(nodes.where((F.col("label") == label) | F.lit(label == "*")).select("id"), "id")
    return now


def _below(edges: DataFrame, start: DataFrame) -> DataFrame:
    seen = front = cut(start)
    while not front.isEmpty():
        new = front.join(edges, F.col("id") == F.col("parent")).select(F.col("child").alias("id")).distinct()
        front = cut(new.join(seen, "id", "left_anti"))
        seen = cut(seen.union(front))
    return seen


def path_query(index: BisimIndex, path: list[str], anchored: bool = False, direct: LabeledDag | None = None) -> DataFrame:
    """node_id of the nodes at the end of the path, from extents of blocks.

    On a 1-index or a stable F&B-index this is exact, on A(k) for paths of up to k edges; for longer ones give
    ``direct``, on which what the index finds is verified.
    """
    nodes = index.blocks.select(F.col("block_id").alias("id"), "label", "has_root")
    edges = index.edges.select(F.col("parent_block").alias("parent"), F.col("child_block").alias("child"))
    found = _steps(nodes, edges, path, nodes.where("has_root") if anchored else nodes)
    out = index.extents.join(found.withColumnRenamed("id", "block_id"), "block_id").select("node_id")
    return out if direct is None else out.join(path_query_direct(direct, path, anchored), "node_id", "left_semi")


def path_query_direct(g: LabeledDag, path: list[str], anchored: bool = False) -> DataFrame:
    """The same from the graph itself."""
    nodes = g.nodes.select(F.col("node_id").alias("id"), "label")
    first = roots(g).select(F.col("node_id").alias("id"), "label") if anchored else nodes
    return _steps(nodes, g.edges, path, first).withColumnRenamed("id", "node_id")


def twig_query(index: BisimIndex, above: list[str], below: list[str]) -> DataFrame:
    """node_id of nodes that end the path ``above`` and begin the path ``below``; for an F&B-index."""
    nodes = index.blocks.select(F.col("block_id").alias("id"), "label")
    edges = index.edges.select(F.col("parent_block").alias("parent"), F.col("child_block").alias("child"))
    turned = edges.select(F.col("child").alias("parent"), F.col("parent").alias("child"))
    down = _steps(nodes, turned, below[::-1], nodes)
    both = _steps(nodes, edges, above, nodes).join(down, "id", "left_semi")
    return index.extents.join(both.withColumnRenamed("id", "block_id"), "block_id").select("node_id")


def twig_query_direct(g: LabeledDag, above: list[str], below: list[str]) -> DataFrame:
    nodes = g.nodes.select(F.col("node_id").alias("id"), "label")
    turned = g.edges.select(F.col("child").alias("parent"), F.col("parent").alias("child"))
    return _steps(nodes, g.edges, above, nodes).join(_steps(nodes, turned, below[::-1], nodes), "id", "left_semi").withColumnRenamed("id", "node_id")


def index_stats(index: BisimIndex) -> DataFrame:
    """nodes, blocks, edges, largest, singletons: one row."""
    b = index.blocks.agg(F.coalesce(F.sum("n_members"), F.lit(0)).alias("nodes"), F.count("*").alias("blocks"), F.coalesce(F.max("n_members"), F.lit(0)).alias("largest"), F.coalesce(F.sum((F.col("n_members") == 1).cast("long")), F.lit(0)).alias("singletons"))
    return b.crossJoin(index.edges.agg(F.count("*").alias("edges"))).select("nodes", "blocks", "edges", "largest", "singletons")  # one row each
