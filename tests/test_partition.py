import pytest

from dagquotient.functions.lineage import cut
from dagquotient.operators import graph, index, partition, ranks, refine, renumber
from dagquotient.sources import fixtures, generate
from tests import brute


def build(spark, nodes, edges):
    return graph.LabeledDag(spark.createDataFrame(nodes, "node_id long, label string"), spark.createDataFrame(edges, "parent long, child long"))


def blocks(df):
    return {r["node_id"]: r["block_id"] for r in df.collect()}


@pytest.fixture(scope="module")
def sample(spark):
    nodes, edges = brute.random_graph(7)
    return build(spark, nodes, edges).cut(), *brute.forward(nodes, edges)


@pytest.mark.parametrize("how", ["peeling", "supersteps", "blocks", "relaxation"])
def test_ranks_agree(sample, how):
    g, _, rank = sample
    df = {"peeling": lambda: ranks.by_peeling(g), "supersteps": lambda: ranks.by_peeling(g, fuse_rows=0), "blocks": lambda: ranks.by_blocks(g, 3), "relaxation": lambda: ranks.by_relaxation(g)}[how]()
    assert {r["node_id"]: r["rank"] for r in df.collect()} == rank


@pytest.mark.parametrize("combine", ["commutative", "sorted"])
def test_all_ways_give_the_same_hashes(spark, combine):
    hub = build(spark, [(k, f"l{k % 7}" if k % 5 else None) for k in range(60)], [(59, k) for k in range(50)] + [(k, k - 30) for k in range(30, 58)]).cut()

    def rows(df):
        return {(r["node_id"], r["rank"], r["label"], r["hash"]) for r in df.collect()}

    want = rows(ranks.by_peeling(hub, combine=combine))
    assert rows(ranks.by_peeling(hub, 64, 0, combine)) == rows(ranks.by_peeling(hub, 64, 90, combine)) == rows(ranks.by_blocks(hub, 2, combine=combine)) == want
    short = rows(ranks.by_peeling(hub, 5, 10**6, combine))
    assert short == rows(ranks.by_peeling(hub, 5, 0, combine)) and all(0 <= r[3] < 32 for r in short)


def test_unknown_hash_is_told(sample):
    with pytest.raises(ValueError):
        ranks.by_peeling(sample[0], combine="other")


@pytest.mark.parametrize("args", [{}, {"bits": 3}, {"method": "sweep", "initial": "rank"}, {"method": "sweep", "initial": "rank_label", "family": "records", "bits": 2}])
def test_partitions_agree(sample, args):
    g, want, _ = sample
    assert blocks(partition.forward_partition(g, **args)) == want


@pytest.mark.parametrize("how", ["signature", "splitter", "rank"])
def test_baselines_agree(sample, how):
    g, want, _ = sample
    df = {"signature": refine.by_signature, "splitter": refine.by_splitter, "rank": lambda g: refine.by_rank(g, cut(ranks.by_peeling(g)))}[how](g)
    assert blocks(df) == want


def test_checks_tell_coarse_from_fine(spark, sample):
    g, want, _ = sample
    p = cut(partition.forward_partition(g))
    assert partition.unstable(g, p).isEmpty()
    coarse = partition._named(g.nodes, ["label"])
    assert not partition.unstable(g, coarse).isEmpty()
    assert partition.is_refinement(p, coarse).isEmpty() and not partition.is_refinement(coarse, p).isEmpty()
    assert partition.partition_error(p, p).first().asDict() == {"merged": 0, "split": 0}
    assert partition.partition_error(coarse, p).first()["merged"] > 0
    assert partition.same_partition(partition.meet(p, coarse), p)


def test_quotient_is_minimal_and_bisimilar(sample):
    g = sample[0]
    small = index.build_index(g, cut(partition.forward_partition(g))).graph().cut()
    assert blocks(partition.forward_partition(small)) == {r["node_id"]: r["node_id"] for r in small.nodes.collect()}
    assert partition.graphs_bisimilar(g, small).first()["bisimilar"]


def test_k_bounded(sample):
    g = sample[0]
    nodes = [(r["node_id"], r["label"]) for r in g.nodes.collect()]
    edges = [(r["child"], r["parent"]) for r in g.edges.collect()]
    assert blocks(partition.ak_index_graph(g, 2)) == brute.k_partition(nodes, edges, 2)


def test_children_of_all_lower_ranks_count(spark):
    g = build(spark, [(0, "x"), (1, "y"), (2, "y"), (3, "y"), (4, "t"), (5, "t")], [(1, 0), (2, 1), (3, 2), (4, 3), (4, 0), (5, 3)])
    got = blocks(partition.forward_partition(g, "sweep", "rank_label"))
    assert got[4] != got[5]


def test_degenerate_graphs(spark):
    assert blocks(partition.forward_partition(build(spark, [(3, "a"), (4, "a"), (5, "b")], []))) == {3: 3, 4: 3, 5: 5}
    assert blocks(partition.forward_partition(build(spark, [], []))) == {}


def test_faults_are_told(spark):
    g = build(spark, [(0, "a"), (1, None), (1, "b")], [(1, 1), (1, 9), (0, 1)])
    kinds = {r["kind"] for r in graph.validate(g, True).collect()}
    assert kinds == {"duplicate node", "null label", "self loop", "no such child", "child not before parent"}
    cycle = build(spark, [(0, "a"), (1, "a"), (2, "a"), (3, "a")], [(0, 1), (1, 0), (2, 1)])
    with pytest.raises(ranks.CyclicGraph):
        ranks.by_peeling(cycle)
    assert {r["node_id"] for r in ranks.cyclic_residue(cycle).collect()} == {0, 1, 2}


def test_renumbering_orders_ranks(sample):
    g, _, rank = sample
    nodes, edges = renumber.renumbered(g, cut(ranks.by_peeling(g)))
    order = [r["rank"] for r in nodes.orderBy("new_id").collect()]
    assert order == sorted(rank.values())
    assert renumber.check_numbering(nodes, edges).isEmpty() and edges.count() == g.edges.count()


def test_pinned_sizes(spark):
    g = fixtures.graph(spark, "/root/testdata/sf0.001", "containment").cut()
    assert g.size() == (7680, 7675)
    s = index.index_stats(index.build_index(g, cut(partition.forward_partition(g)))).first()
    assert (s["blocks"], s["edges"], s["largest"], s["singletons"]) == (378, 2216, 1066, 180)


def test_generators_make_dags(spark):
    g = generate.random_dag(spark, 500)
    assert g.edges.where("child >= parent").isEmpty() and g.nodes.count() == 500
    assert generate.dense_dag(spark, 30, 100).edges.count() == 30 * 29 // 2


def test_splitters_in_one_task_and_in_rounds(spark):
    """More nodes than one Spark round a block was allowed for, and rounds against the one task; null labels are a label."""
    many = graph.LabeledDag(spark.range(10_400).selectExpr("id AS node_id", "IF(id % 2 = 0, 'a', 'b') AS label"), spark.range(10_400).where("id % 4 > 0").selectExpr("id AS parent", "id - 1 AS child"))
    assert {r["node_id"]: r["block_id"] for r in refine.by_splitter(many).collect()} == {i: i % 4 for i in range(10_400)}
    few = graph.LabeledDag(spark.range(12).selectExpr("id AS node_id", "IF(id % 3 = 0, NULL, 'a') AS label"), spark.createDataFrame([(3, 0), (4, 1), (5, 2), (6, 4), (9, 3), (9, 5), (10, 5), (10, 4)], "parent long, child long")).cut()
    one, rounds = (sorted(map(tuple, refine.by_splitter(few, n).collect())) for n in (refine.FUSE_ROWS, 0))
    assert one == rounds
