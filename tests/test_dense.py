import pytest

from dagquotient.operators import partition, ranks
from dagquotient.sources import fixtures
from tests import brute
from tests.test_partition import blocks, build


def rows(df):
    return sorted(map(tuple, df.collect()), key=lambda r: r[0])


def test_edges_that_fit_as_bits_take_no_rounds(spark, monkeypatch):
    """All pairs of 150 nodes, with numbers far apart: as many ranks as nodes, in a few jobs and not in rounds."""
    nodes = [(7 + 10**6 * i, None if i % 50 == 3 else "abc"[i % 3]) for i in range(150)]
    g = build(spark, nodes, [(a, b) for a, _ in nodes for b, _ in nodes if b < a]).cut()
    want = rows(ranks.by_peeling(g))
    tables, cut = [], ranks.cut
    monkeypatch.setattr(ranks, "cut", lambda df: tables.append(1) or cut(df))
    assert rows(ranks.by_peeling(g, fuse_rows=2000)) == want and [r[1] for r in want] == list(range(150))
    assert len(tables) <= 4


def test_bits_give_the_same_as_rounds(spark, monkeypatch):
    """Classes of several members, hashes of few bits that meet across ranks, and what earlier rounds have sent."""
    nodes, edges = brute.random_graph(11, n=60, labels=2, degree=3)
    g = build(spark, nodes, edges).cut()
    for bits in (64, 4):
        want = rows(ranks.by_peeling(g, bits, fuse_rows=0))
        assert rows(ranks.by_peeling(g, bits, fuse_rows=len(edges))) == want
        with monkeypatch.context() as m:  # too many words until some rounds are done
            m.setattr(ranks, "ROW_WORDS", 0.4)
            assert rows(ranks.by_peeling(g, bits, fuse_rows=len(edges))) == want


def test_cycles_are_told_by_bits(spark):
    g = build(spark, [(i, "a") for i in range(8)], [(0, 1), (1, 0), (2, 1), (4, 3), (5, 4), (6, 5), (7, 6)]).cut()
    done, left = ranks._peel(g, 64, 5, "commutative")
    assert {r[0] for r in left.select("node_id").collect()} == {0, 1, 2} and {r[0]: r[1] for r in done.collect()} == {3: 0, 4: 1, 5: 2, 6: 3, 7: 4}


def test_dense_graph_is_a_set_of_edges(spark, tmp_path):
    """Keys that come twice give no edge twice."""
    keys = spark.read.parquet("/root/testdata/sf0.001/supplier.parquet")
    keys.union(keys).union(keys.selectExpr("s_suppkey + 100 AS s_suppkey", *keys.columns[1:])).write.parquet(f"{tmp_path}/supplier.parquet")
    got = sorted(map(tuple, fixtures.graph(spark, str(tmp_path), "dense50").edges.collect()))
    ids = {r[0] for r in keys.select("s_suppkey").collect()} | {r[0] + 100 for r in keys.select("s_suppkey").collect()}
    assert got == sorted((p, c) for p in ids for c in ids if p > c and (p * 7919 + c * 104729) % 1000 < 500)


def test_partition_of_a_dense_graph(spark):
    nodes, edges = brute.random_graph(5, n=90, labels=1, degree=12)
    g = build(spark, nodes, edges).cut()
    want, _ = brute.forward(nodes, edges)
    assert blocks(partition.certified(g, ranks.by_peeling(g, fuse_rows=len(edges)))) == want
    assert blocks(partition.certified(g, ranks.by_peeling(g, 3, fuse_rows=len(edges)))) == want


def test_supersteps_of_a_deep_graph_take_few_rounds(spark, monkeypatch):
    """All pairs of 150 nodes: as many ranks as nodes, in a few steps of bounded tasks."""
    g = build(spark, [(7 + 10**6 * i, "a") for i in range(150)], [(7 + 10**6 * a, 7 + 10**6 * b) for a in range(150) for b in range(a)]).cut()
    tables, cut = [], ranks.cut
    monkeypatch.setattr(ranks, "cut", lambda df: tables.append(1) or cut(df))
    assert [r[1] for r in rows(ranks.by_supersteps(g, step_rows=2000))] == list(range(150))
    assert len(tables) <= 20


def test_supersteps_agree_with_peeling(spark):
    nodes, edges = brute.random_graph(3, n=80, labels=2, degree=3)
    g = build(spark, nodes, edges).cut()
    want = [(r[0], r[1]) for r in rows(ranks.by_peeling(g))]
    for thin, held in ((0, 0), (5, 40), (1000, 60), (1000, 10**6)):
        assert rows(ranks.by_supersteps(g, thin, held)) == want
    empty = build(spark, nodes, edges)
    assert ranks.by_supersteps(type(g)(empty.nodes.limit(0), empty.edges.limit(0))).count() == 0


def test_supersteps_tell_cycles(spark):
    g = build(spark, [(i, "a") for i in range(8)], [(0, 1), (1, 0), (2, 1), (4, 3), (5, 4), (6, 5), (7, 6)]).cut()
    for thin in (0, 1000):
        with pytest.raises(ranks.CyclicGraph):
            ranks.by_supersteps(g, thin)
