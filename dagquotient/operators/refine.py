"""The refinement methods that rank sweeps are compared with; they need no ranks and hold on cyclic graphs too."""

from __future__ import annotations

from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagquotient.functions.lineage import cut
from dagquotient.operators.graph import LabeledDag
from dagquotient.operators.partition import _named, families
from dagquotient.operators.ranks import FUSE_ROWS


def _n_blocks(partition: DataFrame) -> int:
    return partition.select("block_id").distinct().count()


def by_signature(g: LabeledDag, start: DataFrame | None = None, max_rounds: int = 100_000) -> DataFrame:
    """All blocks are split at once by (block, set of child blocks), until their number stays."""
    partition = cut(_named(g.nodes, ["label"])) if start is None else start
    n = _n_blocks(partition)
    for _ in range(max_rounds):
        step = cut(families(g, partition).join(partition.withColumnRenamed("block_id", "before"), "node_id"))
        partition = cut(_named(step, ["before", "family"]))
        if (more := _n_blocks(partition)) == n:
            return partition
        n = more
    raise RuntimeError(f"not stable after {max_rounds} rounds")


def by_splitter(g: LabeledDag, fuse_rows: int = FUSE_ROWS) -> DataFrame:
    """One block at a time splits all others by whether their nodes have a child in it.

    One task does all of it on a graph of up to ``fuse_rows`` nodes and edges; on a larger one, a block is a Spark round.
    """
    if sum(g.size()) <= fuse_rows:
        rows = g.nodes.select(F.col("node_id").alias("a"), F.lit(None).cast("long").alias("b"), "label")
        rows = rows.unionByName(g.edges.select(F.col("parent").alias("a"), F.col("child").alias("b"), F.lit(None).cast("string").alias("label")))
        return rows.groupBy(F.lit(0).alias("one")).applyInArrow(_split_all, "node_id long, block_id long")
    partition = cut(_named(g.nodes, ["label"]))
    todo = [r["block_id"] for r in partition.select("block_id").distinct().orderBy("block_id").collect()]  # a label each
    while todo:
        splitter = todo.pop(0)
        inside = partition.where(F.col("block_id") == splitter).select(F.col("node_id").alias("child"))
        hit = g.edges.join(inside, "child", "left_semi").select(F.col("parent").alias("node_id"), F.lit(True).alias("hit")).distinct()
        step = partition.withColumnRenamed("block_id", "before").join(hit, "node_id", "left").withColumn("hit", F.coalesce("hit", F.lit(False)))
        new = cut(_named(cut(step), ["before", "hit"]))
        changed = new.join(partition.withColumnRenamed("block_id", "before"), "node_id").groupBy("before").agg(F.collect_set("block_id").alias("parts")).where(F.size("parts") > 1).collect()
        if changed:
            split = {r["before"]: r["parts"] for r in changed}
            todo = [x for x in todo if x not in split] + [x for parts in split.values() for x in sorted(parts)]
            partition = new
    return partition


def _split_all(table: pa.Table) -> pa.Table:
    """Every splitter in turn, on arrays; rows without b are nodes, others edges."""
    import pyarrow.compute as pc

    edge = pc.is_valid(table.column("b"))
    named, pairs = table.filter(pc.invert(edge)).sort_by("a"), table.filter(edge)
    ids = named.column("a").to_numpy().astype(np.int64)
    labels = named.column("label").combine_chunks().dictionary_encode()
    block = labels.indices.fill_null(len(labels.dictionary)).to_numpy(zero_copy_only=False).astype(np.int64)
    parent, child = (pairs.column(c).to_numpy().astype(np.int64) for c in ("a", "b"))
    inside = np.isin(parent, ids) & np.isin(child, ids)
    parent, child = np.searchsorted(ids, parent[inside]), np.searchsorted(ids, child[inside])
    order = np.argsort(child, kind="stable")
    above, begin = parent[order], np.concatenate([[0], np.cumsum(np.bincount(child, minlength=len(ids)))]).astype(np.int64)
    members = {int(k): np.flatnonzero(block == k) for k in np.unique(block)}
    fresh, todo = max(members, default=0) + 1, deque(members)
    waiting = set(todo)
    while todo:
        splitter = todo.popleft()
        waiting.discard(splitter)
        nodes = members[splitter]
        many = begin[nodes + 1] - begin[nodes]
        hit = np.unique(above[np.arange(int(many.sum())) + np.repeat(begin[nodes] - (np.cumsum(many) - many), many)])
        hit = hit[np.argsort(block[hit], kind="stable")]
        for part in np.split(hit, np.flatnonzero(np.diff(block[hit])) + 1) if len(hit) else []:
            old = int(block[part[0]])
            if len(part) == len(members[old]):
                continue
            members[old], members[fresh] = np.setdiff1d(members[old], part, assume_unique=True), part
            block[part] = fresh
            for x in (old, fresh):
                if x not in waiting:
                    waiting.add(x)
                    todo.append(x)
            fresh += 1
    smallest = np.full(fresh, np.iinfo(np.int64).max)
    np.minimum.at(smallest, block, ids)
    return pa.table({"node_id": ids, "block_id": smallest[block]})


def by_rank(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """Refinement helped by ranks: from (rank, label), the blocks of each rank split those above, lowest rank first."""
    partition = cut(_named(ranked, ["rank", "label"]))
    top = ranked.agg(F.max("rank")).first()[0] or 0
    rank_of = ranked.select(F.col("node_id").alias("child"), "rank")
    edges = cut(g.edges.join(rank_of, "child"))
    for r in range(top):
        told = edges.where(F.col("rank") == r).join(partition.select(F.col("node_id").alias("child"), "block_id"), "child").select(F.col("parent").alias("node_id"), "block_id").distinct()
        sets = told.groupBy("node_id").agg(F.array_sort(F.collect_list("block_id")).alias("family"))
        step = partition.withColumnRenamed("block_id", "before").join(sets, "node_id", "left").withColumn("family", F.coalesce("family", F.array().cast("array<long>")))
        partition = cut(_named(cut(step), ["before", "family"]))
    return partition
