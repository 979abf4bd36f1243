"""Labelled DAGs: a table of nodes, a set of edges, checks of both and simple transformations."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagquotient.functions.lineage import cut


@dataclass(frozen=True)
class LabeledDag:
    """nodes: node_id, label. edges: parent, child, a set (use ``of`` to drop repeated edges)."""

    nodes: DataFrame
    edges: DataFrame

    @staticmethod
    def of(nodes: DataFrame, edges: DataFrame) -> LabeledDag:
        nodes = nodes.select(F.col("node_id").cast("long").alias("node_id"), F.col("label").cast("string").alias("label"))
        edges = edges.select(F.col("parent").cast("long").alias("parent"), F.col("child").cast("long").alias("child")).dropDuplicates(["parent", "child"])
        return LabeledDag(nodes, edges)

    def cut(self) -> LabeledDag:
        """The same graph, read from tables in the shared folder."""
        return LabeledDag(cut(self.nodes), cut(self.edges))

    def reverse(self) -> LabeledDag:
        """Edges turned round: forward methods on it are backward ones here."""
        return LabeledDag(self.nodes, self.edges.select(F.col("child").alias("parent"), F.col("parent").alias("child")))

    def size(self) -> tuple[int, int]:
        return self.nodes.count(), self.edges.count()


def disjoint_union(*graphs: LabeledDag) -> tuple[LabeledDag, DataFrame]:
    """One graph of all, and node_id, graph_no, origin of its nodes: node_id = origin * number of graphs + graph_no."""
    many = len(graphs)

    def moved(c: str, k: int):
        return (F.col(c) * many + k).alias(c)

    nodes = edges = names = None
    for k, g in enumerate(graphs):
        n, e = g.nodes.select(moved("node_id", k), "label"), g.edges.select(moved("parent", k), moved("child", k))
        o = g.nodes.select(moved("node_id", k), F.lit(k).alias("graph_no"), F.col("node_id").alias("origin"))
        nodes, edges, names = (n, e, o) if nodes is None else (nodes.unionByName(n), edges.unionByName(e), names.unionByName(o))
    return LabeledDag(nodes, edges), names


def degrees(g: LabeledDag) -> DataFrame:
    """node_id, children, parents."""
    down = g.edges.groupBy(F.col("parent").alias("node_id")).agg(F.count("*").alias("children"))
    up = g.edges.groupBy(F.col("child").alias("node_id")).agg(F.count("*").alias("parents"))
    return g.nodes.select("node_id").join(down, "node_id", "left").join(up, "node_id", "left").na.fill(0)


def leaves(g: LabeledDag) -> DataFrame:
    return g.nodes.join(g.edges.select(F.col("parent").alias("node_id")), "node_id", "left_anti")


def roots(g: LabeledDag) -> DataFrame:
    return g.nodes.join(g.edges.select(F.col("child").alias("node_id")), "node_id", "left_anti")


def children_of(g: LabeledDag, start: DataFrame) -> DataFrame:
    """parent, child of the edges that leave the node_ids of ``start``."""
    return g.edges.join(start.select(F.col("node_id").alias("parent")).distinct(), "parent", "left_semi")


def parents_of(g: LabeledDag, start: DataFrame) -> DataFrame:
    """parent, child of the edges that end at the node_ids of ``start``."""
    return children_of(g.reverse(), start).select(F.col("child").alias("parent"), F.col("parent").alias("child"))


def validate(g: LabeledDag, require_topological: bool = False) -> DataFrame:
    """kind, a, b: what is wrong with the graph, no row if nothing is. Cycles are told by ``ranks.cyclic_residue``."""
    none = F.lit(None).cast("long")
    ids = g.nodes.select("node_id")

    def found(df: DataFrame, kind: str, a, b=none) -> DataFrame:
        return df.select(F.lit(kind).alias("kind"), a.alias("a"), b.alias("b"))

    out = found(ids.groupBy("node_id").count().where("count > 1"), "duplicate node", F.col("node_id"))
    out = out.unionByName(found(g.nodes.where("label IS NULL"), "null label", F.col("node_id")))
    out = out.unionByName(found(g.edges.where("parent = child"), "self loop", F.col("parent"), F.col("child")))
    for end in ("parent", "child"):
        loose = g.edges.join(ids.withColumnRenamed("node_id", end), end, "left_anti")
        out = out.unionByName(found(loose, f"no such {end}", F.col("parent"), F.col("child")))
    if require_topological:
        out = out.unionByName(found(g.edges.where("child >= parent"), "child not before parent", F.col("parent"), F.col("child")))
    return out


def descendants(g: LabeledDag, start: DataFrame) -> LabeledDag:
    """The part of ``g`` below the node_ids of ``start``, themselves included: a sample that keeps families whole."""
    seen = cut(start.select("node_id").distinct())
    front = seen
    while not front.isEmpty():
        below = g.edges.join(front.withColumnRenamed("node_id", "parent"), "parent", "left_semi").select(F.col("child").alias("node_id")).distinct()
        front = cut(below.join(seen, "node_id", "left_anti"))
        seen = cut(seen.unionByName(front))
    return LabeledDag(g.nodes.join(seen, "node_id", "left_semi"), g.edges.join(seen.withColumnRenamed("node_id", "parent"), "parent", "left_semi"))
