"""Cost measures: block transfers as the external-memory model predicts them, and what is counted on real graphs."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.operators.graph import LabeledDag


@dataclass(frozen=True)
class IoModel:
    """A fast memory of ``memory`` units and transfers of ``block`` units."""

    memory: int
    block: int

    def scan(self, n: int) -> int:
        return math.ceil(n / self.block)

    def sort(self, n: int) -> int:
        """n/B times log_{M/B}(n/B), at least one pass."""
        blocks = n / self.block
        if n <= self.memory or blocks <= 1:
            return self.scan(n)
        return math.ceil(blocks * max(1.0, math.log(blocks) / math.log(max(2.0, self.memory / self.block))))

    def predict(self, kind: str, nodes: int, edges: int = 0, k: int = 0) -> int:
        """Transfers of a method: general, queue, families, group, one_index or ak."""
        return {
            "general": lambda: self.sort(nodes + edges),
            "queue": lambda: self.sort(edges),
            "families": lambda: self.sort(edges),
            "group": lambda: self.scan(nodes + 2 * edges),
            "one_index": lambda: self.sort(nodes),
            "ak": lambda: self.sort(max(1, k) * nodes),
        }[kind]()


def predicted(spark: SparkSession, nodes: int, edges: int, k: int = 2, memory: int = 2**20, block: int = 2**12) -> DataFrame:
    model = IoModel(memory, block)
    return spark.createDataFrame([(kind, model.predict(kind, nodes, edges, k)) for kind in ("general", "queue", "families", "group", "one_index", "ak")], "kind string, transfers long")


def messages_per_rank(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """rank, inserts, extracts: messages that nodes of a rank send and get; each sums to the number of edges."""
    rank_of = ranked.select("node_id", "rank")
    sent = g.edges.join(rank_of.withColumnRenamed("node_id", "child"), "child").groupBy("rank").agg(F.count("*").alias("inserts"))
    got = g.edges.join(rank_of.withColumnRenamed("node_id", "parent"), "parent").groupBy("rank").agg(F.count("*").alias("extracts"))
    return sent.join(got, "rank", "full").na.fill(0)


def queue_peak(g: LabeledDag, ranked: DataFrame) -> DataFrame:
    """peak: the most messages under way between two ranks. One row; the window is over one row a rank."""
    over = Window.orderBy("rank")
    waiting = F.sum("inserts").over(over) - F.sum("extracts").over(over)
    return messages_per_rank(g, ranked).select(waiting.alias("waiting")).agg(F.coalesce(F.max("waiting"), F.lit(0)).alias("peak"))


def initial_blocks(ranked: DataFrame) -> DataFrame:
    """start, blocks, largest: the groups that phase 2 begins with, by rank and label and with hashes."""
    out = None
    for name, keys in (("rank_label", ["rank", "label"]), ("rank_label_hash", ["rank", "label", "hash"])):
        one = ranked.groupBy(*keys).agg(F.count("*").alias("n")).agg(F.count("*").alias("blocks"), F.coalesce(F.max("n"), F.lit(0)).alias("largest")).select(F.lit(name).alias("start"), "blocks", "largest")
        out = one if out is None else out.unionByName(one)
    return out


def hash_tradeoff(nodes: int, edges: int) -> dict[str, float]:
    """Numbers moved a node: for a hash eight at most; for sorting group records in four passes that it may save."""
    record = 1 + 2 * edges / max(1, nodes)
    return {"hash": 8.0, "group_record": record, "saved": 4 * record}


def blocks_per_node(partition: DataFrame) -> DataFrame:
    return partition.agg(F.count("*").alias("nodes"), F.countDistinct("block_id").alias("blocks"))
