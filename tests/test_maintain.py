"""Maintained partitions are those of the whole graph."""

import pytest

from dagquotient.operators import maintain
from dagquotient.operators.graph import LabeledDag
from dagquotient.operators.partition import forward_partition


def rows(df):
    return {tuple(r) for r in df.select("node_id", "block_id").collect()}


def dag(spark, nodes, edges):
    return LabeledDag.of(spark.createDataFrame(nodes, "node_id long, label string"), spark.createDataFrame(edges, "parent long, child long")).cut()


NODES = [(i, None if i == 3 else "ab"[i % 2]) for i in range(1, 13)]
EDGES = [(p, c) for p in range(1, 13) for c in range(1, p) if (p * 7 + c * 5) % 5 == 0]


@pytest.mark.parametrize("old", [0, 6])
def test_append(spark, old):
    g = dag(spark, NODES[:old], [e for e in EDGES if e[0] <= old])
    new = spark.createDataFrame(NODES[old:], "node_id long, label string")
    edges = spark.createDataFrame([e for e in EDGES if e[0] > old], "parent long, child long")
    found = maintain.append_nodes(g, forward_partition(g), new, edges)
    assert rows(maintain.renamed(found)) == rows(forward_partition(dag(spark, NODES, EDGES)))


def test_appended_nodes_of_smaller_ids_join_old_blocks(spark):
    g = dag(spark, [(10, "a"), (11, "b")], [(11, 10)])
    found = maintain.append_nodes(g, forward_partition(g), spark.createDataFrame([(1, "a"), (2, "b")], "node_id long, label string"), spark.createDataFrame([(2, 1)], "parent long, child long"))
    assert rows(found) == {(10, 10), (11, 11), (1, 10), (2, 11)}


@pytest.mark.parametrize("inserted, deleted", [([(9, 2)], EDGES[::4]), ([], [])])
def test_edge_changes(spark, inserted, deleted):
    g = dag(spark, NODES, EDGES)
    ins, dele = (spark.createDataFrame(x, "parent long, child long") for x in (inserted, deleted))
    expected = rows(forward_partition(dag(spark, NODES, sorted({*EDGES} - {*deleted} | {*inserted}))))
    assert rows(maintain.edge_changes(g, forward_partition(g), ins, dele)) == expected
    assert rows(maintain.recompute(g, ins, dele)) == expected
