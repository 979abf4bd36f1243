"""The experiments as measured runs: each gives the rows of a ``CostLedger``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from dagquotient.functions.lineage import cut
from dagquotient.operators import partition, ranks, renumber, tree
from dagquotient.operators.graph import LabeledDag
from dagquotient.plans.ledger import CostLedger
from dagquotient.sources import fixtures


def phases(spark: SparkSession, g: LabeledDag, starts: tuple[str, ...] = ("rank_label", "rank_label_hash")) -> CostLedger:
    """Ranking, renumbering and grouping of one graph, each on its own; grouping from every start."""
    g = g.cut()
    items, ledger = sum(g.size()), CostLedger(spark)
    with ledger.phase("forward", "rank", items):
        ranked = cut(ranks.by_peeling(g))
    with ledger.phase("forward", "renumber", items):
        for df in renumber.renumbered(g, ranked):
            cut(df)
    for start in starts:
        with ledger.phase("forward", f"group from {start}", items):
            cut(partition.forward_partition(g, "sweep", start, ranked=ranked))
    with ledger.phase("forward", "certify hashes", items):
        cut(partition.certified(g, ranked))
    return ledger


def memory(spark: SparkSession, g: LabeledDag, shares: tuple[float, ...] = (1.0, 0.25, 0.0625)) -> CostLedger:
    """Ranking under a falling bound on the rows that one task may hold, told as a share of the graph's rows.

    Of a graph that is larger than a task may hold (``ranks.FUSE_ROWS``), the shares are of that bound.

    Memory of executors is fixed when a session starts; the bound is what the method itself keeps in memory.
    """
    g = g.cut()
    items, ledger = sum(g.size()), CostLedger(spark)
    for share in shares:
        with ledger.phase("rank", f"{share:g} of the rows", items):
            cut(ranks.by_peeling(g, fuse_rows=int(min(items, ranks.FUSE_ROWS) * share)))
    return ledger


def trees(spark: SparkSession, documents: DataFrame, methods: tuple[str, ...] = ("general", "path", "sweep")) -> CostLedger:
    """The 1-index of documents by each method; costs are told for a node."""
    documents = cut(documents)
    nodes, ledger = documents.count(), CostLedger(spark)
    for method in methods:
        with ledger.phase(f"one_index {method}", "all", nodes):
            cut(tree.one_index(documents, method))
    return ledger


QUERIES = {
    "experiment_phases": lambda spark, d: phases(spark, fixtures.graph(spark, d, "containment")).table(),
    "experiment_memory": lambda spark, d: memory(spark, fixtures.graph(spark, d, "containment"), (1.0, 0.1, 0.0)).table(),
    "experiment_trees": lambda spark, d: trees(spark, fixtures.page_trees(spark, d), ("general", "path")).table(),
}
