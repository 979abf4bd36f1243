import pytest

from dagquotient.functions.lineage import cut
from dagquotient.operators import index, partition, tree
from dagquotient.plans.cost import IoModel
from dagquotient.sources import fixtures


def blocks(df):
    return {r["node_id"]: r["block_id"] for r in df.collect()}


@pytest.fixture(scope="module")
def figure(spark):
    return cut(tree.rooted(fixtures.literal(spark, fixtures.TREE)))


def sizes(t, p):
    s = index.index_stats(index.build_index(tree.graph_of(t), cut(p))).first()
    return s["blocks"], s["edges"]


def test_figure_indexes(figure):
    for method in ("sweep", "path", "general"):
        assert sizes(figure, tree.one_index(figure, method)) == (7, 6)
    assert sizes(figure, tree.fb_index(figure, "meet")) == (8, 9)
    assert sizes(figure, tree.fb_index(figure)) == sizes(figure, tree.fb_index(figure, "fixpoint")) == (10, 9)
    assert [sizes(figure, tree.blocks_of(tree.ak_doubling(figure, k))) for k in range(4)] == [(3, 3), (4, 4), (5, 6), (7, 6)]


def test_traces_agree(figure):
    for k in (0, 1, 2, 5):
        a, b = (sorted((r["node_id"], tuple(r["trace"])) for r in f(figure, k).collect()) for f in (tree.ak_joins, tree.ak_doubling))
        assert a == b
    assert blocks(tree.blocks_of(tree.ak_joins(figure, 2))) == blocks(partition.ak_index_graph(tree.graph_of(figure), 2))


def test_repair():
    got = list(tree.balanced('<!DOCTYPE html><p><b>x<br><!-- <i> --></u><script>"</p>"</script></p><i>'))
    assert got == [(True, "p"), (True, "b"), (True, "br"), (False, "br"), (True, "script"), (False, "script"), (False, "b"), (False, "p"), (True, "i"), (False, "i")]
    assert list(tree.balanced(None)) == []


def test_levels_of_the_figure(spark):
    html = "<a><a><b/><c/></a><a><b/><c/><a><b/><c/></a></a></a>".replace("<b/>", "<b></b>").replace("<c/>", "<c></c>")
    stream = cut(tree.tags(spark.createDataFrame([(0, html)], "page_id long, html string")))
    nodes, edges = tree.levels(stream)
    got = sorted((r["depth"], r["id_on_level"], r["label"]) for r in nodes.collect())
    assert got == [(0, 0, "a"), (1, 0, "a"), (1, 1, "a"), (2, 0, "b"), (2, 1, "c"), (2, 2, "b"), (2, 3, "c"), (2, 4, "a"), (3, 0, "b"), (3, 1, "c")]
    assert sorted((r["parent_depth"], r["parent_id"], r["child_id"]) for r in edges.collect()) == [(0, 0, 0), (0, 0, 1), (1, 0, 0), (1, 0, 1), (1, 1, 2), (1, 1, 3), (1, 1, 4), (2, 4, 0), (2, 4, 1)]
    t = tree.tree_of(stream)
    assert blocks(tree.blocks_of(tree.ak_stack(stream, 2))) == blocks(tree.blocks_of(tree.ak_joins(t, 2)))


def test_pad_is_reserved(spark):
    t = spark.createDataFrame([(0, None, 0, "#", 0)], "node_id long, parent long, depth int, label string, doc_id long")
    with pytest.raises(ValueError):
        tree.ak_joins(t, 1)


def test_paths_by_index_and_directly(figure):
    g = tree.graph_of(figure)
    one = index.build_index(g, cut(tree.one_index(figure)))
    for path, anchored in ((["a", "b"], False), (["a", "a", "a", "c"], True), (["a", "*", "b"], True), (["a", "**", "c"], True)):
        a, b = (sorted(r["node_id"] for r in df.collect()) for df in (index.path_query(one, path, anchored), index.path_query_direct(g, path, anchored)))
        assert a == b
    both = index.build_index(g, cut(tree.fb_index(figure)))
    assert sorted(r["node_id"] for r in index.twig_query(both, ["a", "a"], ["a", "a", "b"]).collect()) == sorted(r["node_id"] for r in index.twig_query_direct(g, ["a", "a"], ["a", "a", "b"]).collect()) == [2]


def test_io_model():
    m = IoModel(memory=1024, block=16)
    assert m.scan(100) == 7 and m.sort(1000) == 63
    assert m.sort(2**20) == 2**16 * 16 // 6 + 1
    assert m.predict("one_index", 2**20) == m.sort(2**20)


def test_paths_of_deep_trees_form_no_arrays(spark, monkeypatch):
    """Two chains of 150 elements, deeper than the SQL of the page trees goes; their paths are told by numbers."""
    monkeypatch.setattr(tree, "_doubled", lambda *_: pytest.fail("an array for each path"))
    t = cut(spark.range(300).selectExpr("id AS node_id", "CASE WHEN id % 150 > 0 THEN id - 1 END AS parent", "CAST(id % 150 AS INT) AS depth", "CASE WHEN id % 150 % 3 = 0 THEN 'a' ELSE 'b' END AS label", "id div 150 AS doc_id"))
    assert blocks(tree.one_index(t, "path")) == {i: i % 150 for i in range(300)}
