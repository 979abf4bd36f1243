"""The registered queries of the engine: methods, baselines, measures and workloads, each with its SQL where there is any."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient import oracles as O
from dagquotient.functions.lineage import cut
from dagquotient.operators import graph, index, maintain, partition, ranks, refine, renumber, tree
from dagquotient.plans import cost
from dagquotient.sources import fixtures, generate
from dagquotient.sources.tables import load, sql_over

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}

#: Upper bounds of the longest path at the sizes that SQL is run on.
ROUNDS = {"containment": 5, "reference": 5, "random": 30, "two_tier": 30, "event_chain": 100, "conversation": 12, "event_session": 60, "document_sources": 3, "dense0": 1, "dense1": 24, "dense10": 40, "dense50": 80, "dense100": 105, "pages": 60}


def add(name: str, f: Query, sql: str | None = None) -> None:
    _queries[name] = f
    if sql is not None:
        _oracles[name] = sql


def _graph(name: str, f) -> Query:
    return lambda spark, d: f(fixtures.graph(spark, d, name).cut())


def _ids(df: DataFrame) -> DataFrame:
    return df.select("node_id", "block_id")


def _index(p: Callable) -> Callable:
    return lambda g: index.build_index(g, cut(p(g)))


# --- forward partitions --------------------------------------------------------------------------------------------
for _name in ("containment", "reference", "random", "two_tier", "event_chain", "conversation", "dense0", "dense1", "dense10", "dense50", "dense100", "event_session", "document_sources", "pages"):
    add(f"forward_{_name}", _graph(_name, lambda g: _ids(partition.forward_partition(g))), O.forward(O.ctes(_name), ROUNDS[_name]))
for _name in ("containment", "reference", "random"):
    _sql = O.forward(O.ctes(_name), ROUNDS[_name])
    add(f"quotient_edges_{_name}", _graph(_name, lambda g: _index(partition.forward_partition)(g).edges), O.quotient_edges(_sql))
    add(f"quotient_nodes_{_name}", _graph(_name, lambda g: _index(partition.forward_partition)(g).blocks.select("block_id", "label", "n_members")), O.quotient_nodes(_sql))
_random = O.forward(O.ctes("random"), 30)
_small = O.forward(O.ctes("conversation"), 12)
add("forward_sweep_rank_label", _graph("containment", lambda g: _ids(partition.forward_partition(g, "sweep", "rank_label"))), O.forward(O.ctes("containment"), 5))
add("forward_sweep_rank_label_hash", _graph("containment", lambda g: _ids(partition.forward_partition(g, "sweep", "rank_label_hash"))), O.forward(O.ctes("containment"), 5))
add("forward_sweep_rank", _graph("conversation", lambda g: _ids(partition.forward_partition(g, "sweep", "rank"))), _small)
add("forward_sweep_records", _graph("reference", lambda g: _ids(partition.forward_partition(g, "sweep", "rank_label_hash", "records"))), O.forward(O.ctes("reference"), 5))
add("forward_truncated_hash", _graph("random", lambda g: _ids(partition.forward_partition(g, bits=8))), _random)
add("forward_records_truncated_hash", _graph("conversation", lambda g: _ids(partition.forward_partition(g, "sweep", "rank_label", "records", bits=3))), _small)
add("forward_k2", _graph("reference", lambda g: partition.k_partition(g, 2)), O.k_forward(O.ctes("reference"), 2))
add("baseline_signature_random", _graph("random", lambda g: refine.by_signature(g)), _random)
add("baseline_splitter_conversation", _graph("conversation", lambda g: refine.by_splitter(g)), _small)
add("baseline_rank_refine_containment", _graph("containment", lambda g: refine.by_rank(g, cut(ranks.by_peeling(g)))), O.forward(O.ctes("containment"), 5))

# --- ranks and numbering -------------------------------------------------------------------------------------------
for _name in ("containment", "reference", "random", "event_chain", "conversation", "dense10"):
    add(f"rank_{_name}", _graph(_name, lambda g: ranks.by_peeling(g).select("node_id", "rank")), O.rank(O.ctes(_name)))
add("rank_relaxation_reference", _graph("reference", lambda g: ranks.by_relaxation(g).select("node_id", "rank")), O.rank(O.ctes("reference")))
add("rank_blocks_random", _graph("random", lambda g: ranks.by_blocks(g).select("node_id", "rank")), O.rank(O.ctes("random")))
add("rank_recursive_sql_containment", _graph("containment", lambda g: ranks.by_recursive_sql(g).select("node_id", "rank")), O.rank(O.ctes("containment")))
add("rank_supersteps_random", _graph("random", lambda g: ranks.by_peeling(g, fuse_rows=0).select("node_id", "rank")), O.rank(O.ctes("random")))
add("rank_supersteps_dense10", _graph("dense10", lambda g: ranks.by_supersteps(g)), O.rank(O.ctes("dense10")))
for _start in ("rank_label", "rank_label_hash"):  # the first experiment: both starts on the random graph
    add(f"forward_random_{_start}", _graph("random", lambda g, s=_start: _ids(partition.forward_partition(g, "sweep", s))), _random)
add("rank_supersteps_containment", _graph("containment", lambda g: ranks.by_peeling(g, fuse_rows=0).select("node_id", "rank")), O.rank(O.ctes("containment")))
add("forward_sorted_hash", _graph("containment", lambda g: partition.certified(g, cut(ranks.by_peeling(g, combine="sorted")))), O.forward(O.ctes("containment"), 5))


def _renumbered(g, which: int) -> DataFrame:
    out = renumber.renumbered(g, cut(ranks.by_peeling(g)))[which]
    return out.select("new_id", "node_id", "rank") if which == 0 else out


_ranked = O.rank(O.ctes("random"))
_at = _ranked.rindex("SELECT id AS node_id")
_numbered = f"{_ranked[:_at]}, r AS ({_ranked[_at:]}), z AS (SELECT row_number() OVER (ORDER BY rank, label, node_id) AS new_id, node_id, rank FROM r JOIN n USING (node_id))"
add("renumbered_nodes_random", _graph("random", lambda g: _renumbered(g, 0)), f"{_numbered} SELECT new_id, node_id, rank FROM z")
add("renumbered_edges_random", _graph("random", lambda g: _renumbered(g, 1)), f"{_numbered} SELECT p.new_id AS parent, c.new_id AS child FROM e JOIN z p ON p.node_id = e.parent JOIN z c ON c.node_id = e.child")

# --- document trees ------------------------------------------------------------------------------------------------
_pages = O.ctes("pages")


def _tree(f) -> Query:
    return lambda spark, d: f(cut(fixtures.page_trees(spark, d)))


add("pages_tree_nodes", _tree(lambda t: t.select("node_id", F.coalesce("parent", F.lit(-1)).alias("parent"), F.col("depth").cast("long").alias("depth"), "label")), f"{O.page_ctes()} SELECT node_id, coalesce(parent, -1) AS parent, depth, label FROM t")
add("pages_tree_levels", lambda spark, d: tree.levels(fixtures.page_tags(spark, d))[0].select("node_id", F.col("depth").cast("long").alias("depth"), "id_on_level"), f"{O.page_ctes()} SELECT node_id, depth, row_number() OVER (PARTITION BY doc, depth ORDER BY node_id) - 1 AS id_on_level FROM t")
add("pages_tree_levels_chunked", lambda spark, d: tree.levels_in_chunks(fixtures.page_tags(spark, d), 16)[0].select("node_id", F.col("depth").cast("long").alias("depth"), "id_on_level"), f"{O.page_ctes()} SELECT node_id, depth, row_number() OVER (PARTITION BY doc, depth ORDER BY node_id) - 1 AS id_on_level FROM t")
_levels = "l AS (SELECT doc, node_id, parent, depth, row_number() OVER (PARTITION BY doc, depth ORDER BY node_id) - 1 AS k FROM t)"
add("pages_tree_edges", lambda spark, d: tree.levels(fixtures.page_tags(spark, d))[1].select("doc_id", F.col("parent_depth").cast("long").alias("parent_depth"), "parent_id", "child_id"), f"{O.page_ctes()}, {_levels} SELECT c.doc AS doc_id, p.depth AS parent_depth, p.k AS parent_id, c.k AS child_id FROM l c JOIN l p ON p.node_id = c.parent")
for _method in ("path", "general"):
    add(f"pages_one_index_{_method}", _tree(lambda t, m=_method: tree.one_index(t, m)), O.backward(_pages, 60))
add("containment_one_index", lambda spark, d: tree.one_index(fixtures.containment_tree(spark, d)), O.backward(O.ctes("containment"), 5))
add("pages_one_index", _tree(lambda t: tree.one_index(t)), O.backward(_pages, 60))
add("pages_fb_stable", _tree(lambda t: tree.fb_index(t)), O.both_ways(_pages, 60, True))
add("pages_fb_meet", _tree(lambda t: tree.fb_index(t, "meet")), O.both_ways(_pages, 60, False))
add("containment_fb_stable", lambda spark, d: tree.fb_index(fixtures.containment_tree(spark, d)), O.both_ways(O.ctes("containment"), 5, True))
for _k in (0, 1, 2, 4, 8):
    add(f"pages_ak{_k}", _tree(lambda t, k=_k: tree.blocks_of(tree.ak_doubling(t, k))), O.k_backward(_pages, _k))
add("pages_ak2_stack", lambda spark, d: tree.blocks_of(tree.ak_stack(fixtures.page_tags(spark, d), 2)), O.k_backward(_pages, 2))
add("pages_ak2_joins", _tree(lambda t: tree.blocks_of(tree.ak_joins(t, 2))), O.k_backward(_pages, 2))
for _k in (1, 2):
    add(f"reference_ak{_k}", _graph("reference", lambda g, k=_k: partition.ak_index_graph(g, k)), O.k_backward(O.ctes("reference"), _k))
    add(f"containment_ak{_k}", _graph("containment", lambda g, k=_k: partition.ak_index_graph(g, k)), O.k_backward(O.ctes("containment"), _k))
_lags = "coalesce(lag(event_type, 2) OVER w, '#') || '/' || coalesce(lag(event_type, 1) OVER w, '#') || '/' || event_type"
add("events_ak2", lambda spark, d: tree.ak_chain(load(spark, d, "events"), ["user_id"], "ts", "event_type", "event_id", 2).select("node_id", F.array_join("trace", "/").alias("trace")), f"SELECT event_id AS node_id, {_lags} AS trace FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)")
add("conversation_ak1", _graph("conversation", lambda g: partition.ak_index_graph(g, 1)), O.k_backward(O.ctes("conversation"), 1))

# --- worked examples -----------------------------------------------------------------------------------------------
_pair, _one = O.literal_ctes(fixtures.PAIR_LEFT, fixtures.PAIR_RIGHT), O.literal_ctes(fixtures.TREE)


def _copies(*parts: tuple[list, list]) -> Query:
    return lambda spark, d: fixtures.literal_copies(spark, d, *parts)


#: The copies' blocks: those of the worked example, of each nation's first supplier.
_first = "min(s_suppkey) OVER (PARTITION BY s_nationkey)"
_blocks_of_copies = lambda rows: f"SELECT CAST(s_suppkey * 16 + node_id AS BIGINT) AS node_id, CAST({_first} * 16 + block_id AS BIGINT) AS block_id FROM supplier, (VALUES {rows}) x(node_id, block_id)"
add("example_pair_partition", lambda spark, d: partition.forward_partition(_copies(fixtures.PAIR_LEFT, fixtures.PAIR_RIGHT)(spark, d)), _blocks_of_copies("(1,1),(6,1),(2,2),(3,2),(7,2),(4,4),(5,4),(8,4),(9,9),(11,9),(10,10),(12,10)"))
add("example_pair_quotient_edges", lambda spark, d: _index(partition.forward_partition)(_copies(fixtures.PAIR_LEFT)(spark, d)).edges, "SELECT CAST(k * 16 + p AS BIGINT) AS parent_block, CAST(k * 16 + c AS BIGINT) AS child_block FROM (SELECT min(s_suppkey) AS k FROM supplier GROUP BY s_nationkey), (VALUES (1,2),(2,4),(9,2),(10,4)) x(p, c)")
add("example_pair_bisimilar", lambda spark, d: partition.graphs_bisimilar(fixtures.literal(spark, fixtures.PAIR_LEFT), fixtures.literal(spark, fixtures.PAIR_RIGHT)), "SELECT true AS bisimilar, 0::BIGINT AS unmatched")


def _example(f) -> Query:
    return lambda spark, d: f(cut(tree.rooted(fixtures.literal(spark, fixtures.TREE))))


add("example_tree_forward", lambda spark, d: partition.forward_partition(_copies(fixtures.TREE)(spark, d)), _blocks_of_copies("(0,0),(1,1),(7,1),(2,2),(3,3),(5,3),(8,3),(4,4),(6,4),(9,4)"))
add("example_tree_one_index", _example(tree.one_index), "SELECT * FROM (VALUES (0,0),(1,1),(2,1),(3,3),(5,3),(4,4),(6,4),(7,7),(8,8),(9,9)) x(node_id, block_id)")
add("example_tree_fb_meet", _example(lambda t: tree.fb_index(t, "meet")), "SELECT * FROM (VALUES (0,0),(1,1),(2,2),(3,3),(5,3),(4,4),(6,4),(7,7),(8,8),(9,9)) x(node_id, block_id)")
add("example_tree_fb_stable", _example(tree.fb_index), "SELECT i AS node_id, i AS block_id FROM range(10) x(i)")
for _k, _rows in enumerate(("(0,0),(1,0),(2,0),(7,0),(3,3),(5,3),(8,3),(4,4),(6,4),(9,4)", "(0,0),(1,1),(2,1),(7,1),(3,3),(5,3),(8,3),(4,4),(6,4),(9,4)", "(0,0),(1,1),(2,1),(7,7),(3,3),(5,3),(8,3),(4,4),(6,4),(9,4)", "(0,0),(1,1),(2,1),(3,3),(5,3),(4,4),(6,4),(7,7),(8,8),(9,9)")):
    add(f"example_tree_ak{_k}", _example(lambda t, k=_k: tree.blocks_of(tree.ak_doubling(t, k))), f"SELECT * FROM (VALUES {_rows}) x(node_id, block_id)")

# --- checks and measures -------------------------------------------------------------------------------------------


def _checks(g) -> DataFrame:
    ranked = cut(ranks.by_peeling(g))
    p = cut(partition.certified(g, ranked))
    by_label = partition._named(ranked, ["rank", "label"])
    rows = [("unstable", partition.unstable(g, p)), ("not within rank and label", partition.is_refinement(p, by_label)), ("hash too fine", partition.is_refinement(partition._named(ranked, ["hash"]), p)), ("k too fine", partition.is_refinement(p, partition.k_partition(g, 2)))]
    out = None
    for name, df in rows:
        one = df.agg(F.count("*").alias("violations")).select(F.lit(name).alias("what"), "violations")
        out = one if out is None else out.unionByName(one)
    return out


add("checks_random", _graph("random", _checks), "SELECT * FROM (VALUES ('unstable', 0::BIGINT), ('not within rank and label', 0), ('hash too fine', 0), ('k too fine', 0)) x(what, violations)")
_rank_of = f"{_ranked[:_at]}, r AS ({_ranked[_at:]})"
_msg = f"{_rank_of}, m AS (SELECT rank, sum(i)::BIGINT AS inserts, sum(x)::BIGINT AS extracts FROM (SELECT r.rank, 1 AS i, 0 AS x FROM e JOIN r ON r.node_id = e.child UNION ALL SELECT r.rank, 0, 1 FROM e JOIN r ON r.node_id = e.parent) GROUP BY rank)"
add("cost_messages_per_rank", _graph("random", lambda g: cost.messages_per_rank(g, cut(ranks.by_peeling(g)))), f"{_msg} SELECT rank, inserts, extracts FROM m")
add("cost_queue_peak", _graph("random", lambda g: cost.queue_peak(g, cut(ranks.by_peeling(g)))), f"{_msg} SELECT max(w)::BIGINT AS peak FROM (SELECT sum(inserts) OVER o - sum(extracts) OVER o AS w FROM m WINDOW o AS (ORDER BY rank))")
add("cost_initial_blocks", _graph("random", lambda g: cost.initial_blocks(cut(ranks.by_peeling(g)))), f"{_rank_of}, {O.signatures('s', 30)}, j AS (SELECT r.rank, n.label, s.sig FROM r JOIN n USING (node_id) JOIN s ON s.id = r.node_id), a AS (SELECT 'rank_label' AS start, count(*) AS c FROM j GROUP BY rank, label), b AS (SELECT 'rank_label_hash' AS start, count(*) AS c FROM j GROUP BY rank, label, sig) SELECT start, count(*) AS blocks, max(c) AS largest FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY start")
add("cost_blocks_per_node", _graph("random", lambda g: cost.blocks_per_node(partition.forward_partition(g))), f"{_random[: _random.rindex('SELECT id')]} SELECT count(*) AS nodes, count(DISTINCT sig) AS blocks FROM s")


def _collisions(g) -> DataFrame:
    ranked = cut(ranks.by_peeling(g))
    return partition.collision_stats(g, cut(partition.certified(g, ranked)), ranked, bits=6)


def _stats(g) -> DataFrame:
    return index.index_stats(_index(partition.forward_partition)(g))


_head, _tail = _random[: _random.rindex("SELECT id")], _random[_random.rindex("SELECT id") :]
_collision_sql = f"""{_head}, q AS ({_tail}), {_rank_of[len(O.ctes('random')) + 1 :].strip().removeprefix(',')},
f AS (SELECT n.node_id, n.label, r.rank, coalesce(string_agg(DISTINCT c.block_id::VARCHAR, ',' ORDER BY c.block_id::VARCHAR), '') AS any_order, list_sort(list(DISTINCT c.block_id) FILTER (WHERE c.block_id IS NOT NULL)) AS family
      FROM n JOIN r USING (node_id) LEFT JOIN e ON e.parent = n.node_id LEFT JOIN q c ON c.node_id = e.child GROUP BY ALL),
k AS (SELECT rank, label, coalesce(len(family), 0) AS size, ('0x' || substr(md5(coalesce(array_to_string(family, ','), '')), 1, 15))::BIGINT % 64 AS key, count(DISTINCT any_order) AS families, count(*) AS nodes FROM f GROUP BY ALL)
SELECT rank, count(*) AS keys, count(*) FILTER (WHERE families > 1) AS colliding_keys, coalesce(sum(nodes) FILTER (WHERE families > 1), 0)::BIGINT AS colliding_nodes FROM k GROUP BY rank"""
add("cost_collisions", _graph("random", _collisions), _collision_sql)
_ref = O.forward(O.ctes("reference"), ROUNDS["reference"])
_ref_at = _ref.rindex("SELECT id AS node_id")
add("cost_index_stats", _graph("reference", _stats), f"{_ref[:_ref_at]}, q AS ({_ref[_ref_at:]}), z AS (SELECT block_id, count(*) AS c FROM q GROUP BY 1), x AS (SELECT DISTINCT a.block_id AS p, b.block_id AS c FROM e JOIN q a ON a.node_id = e.parent JOIN q b ON b.node_id = e.child) SELECT sum(c)::BIGINT AS nodes, count(*) AS blocks, (SELECT count(*) FROM x) AS edges, max(c) AS largest, count(*) FILTER (WHERE c = 1) AS singletons FROM z")
_sorted = lambda x: f"CASE WHEN {x} <= 1048576 OR {x} <= 4096 THEN ceil({x} / 4096) ELSE ceil({x} / 4096 * greatest(1.0, ln({x} / 4096) / ln(256.0))) END"
_io = {"general": _sorted("(v + w)"), "queue": _sorted("w"), "families": _sorted("w"), "group": "ceil((v + 2 * w) / 4096)", "one_index": _sorted("v"), "ak": _sorted("(2 * v)")}
add("cost_predicted_io", lambda spark, d: cost.predicted(spark, *fixtures.graph(spark, d, "random").size()), f"{O.ctes('random')}, s AS (SELECT (SELECT count(*) FROM n) AS v, (SELECT count(*) FROM e) AS w) " + " UNION ALL ".join(f"SELECT '{k}' AS kind, ({x})::BIGINT AS transfers FROM s" for k, x in _io.items()))
_exact_pairs = "(SELECT sum(c * (c - 1) // 2) FROM (SELECT count(*) AS c FROM s GROUP BY sig))"
add("error_of_k2", _graph("reference", lambda g: partition.partition_error(cut(partition.k_partition(g, 2)), cut(partition.forward_partition(g)))), f"{O.ctes('reference')}, {O.signatures('s', 5)}, {O.signatures('k', 2, keep=True)}, j AS (SELECT s.sig AS a, k.sig AS b FROM s JOIN k ON s.id = k.id), p AS (SELECT (SELECT sum(c * (c - 1) // 2) FROM (SELECT count(*) AS c FROM j GROUP BY b)) AS x, (SELECT sum(c * (c - 1) // 2) FROM (SELECT count(*) AS c FROM j GROUP BY a)) AS y, (SELECT sum(c * (c - 1) // 2) FROM (SELECT count(*) AS c FROM j GROUP BY a, b)) AS z) SELECT (x - z)::BIGINT AS merged, (y - z)::BIGINT AS split FROM p")

# --- queries over indexes ------------------------------------------------------------------------------------------


def _path(labels: list[str], anchored: bool = False, k: int | None = None) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        t = cut(fixtures.page_trees(spark, d))
        g = tree.graph_of(t)
        if k is None:
            return index.path_query(index.build_index(g, cut(tree.one_index(t, "path"))), labels, anchored)
        p = cut(tree.blocks_of(tree.ak_doubling(t, k)))
        return index.path_query(index.build_index(g, p), labels, anchored, direct=g if len(labels) - 1 > k or anchored else None)

    return run


add("path_query_pages_nav", _path(["nav", "ul", "li", "a"]), O.path(_pages, ["nav", "ul", "li", "a"]))
add("path_query_pages_anchored", _path(["html", "body", "article", "p"], True), O.path(_pages, ["html", "body", "article", "p"], True))
add("path_query_ak1_verified", _path(["p", "b", "p", "b"], k=1), O.path(_pages, ["p", "b", "p", "b"]))
add("path_query_ak2", _path(["b", "p"], k=2), O.path(_pages, ["b", "p"]))
add("path_query_containment", lambda spark, d: index.path_query(_one_index_of(spark, d), ["region", "nation", "cust:BUILDING"]), O.path(O.ctes("containment"), ["region", "nation", "cust:BUILDING"]))


def _one_index_of(spark: SparkSession, d: str) -> index.BisimIndex:
    t = cut(fixtures.containment_tree(spark, d))
    return index.build_index(tree.graph_of(t), cut(tree.one_index(t)))


def _twig(spark: SparkSession, d: str) -> DataFrame:
    t = cut(fixtures.page_trees(spark, d))
    return index.twig_query(index.build_index(tree.graph_of(t), cut(tree.fb_index(t))), ["article", "p"], ["p", "b", "p"])


add("twig_query_pages", _twig, f"{_pages} SELECT DISTINCT b.node_id FROM n a JOIN e ON e.parent = a.node_id JOIN n b ON b.node_id = e.child JOIN e f ON f.parent = b.node_id JOIN n c ON c.node_id = f.child JOIN e h ON h.parent = c.node_id JOIN n x ON x.node_id = h.child WHERE a.label = 'article' AND b.label = 'p' AND c.label = 'b' AND x.label = 'p'")

# --- maintenance ---------------------------------------------------------------------------------------------------


def _append_orders(spark: SparkSession, d: str) -> DataFrame:
    """The reference graph without every fifth order and its lineitems, to which these are then added."""
    g = fixtures.graph(spark, d, "reference").cut()
    key = F.when(F.floor(F.col("node_id") / 10**14) == 7, F.floor(F.col("node_id") % 10**14 / 1000)).when(F.floor(F.col("node_id") / 10**14) == 6, F.col("node_id") % 10**14)
    late = cut(g.nodes.where(F.coalesce(key % 5 == 0, F.lit(False))))
    ids = late.select(F.col("node_id").alias("parent"))
    old = maintain.LabeledDag(g.nodes.join(late, "node_id", "left_anti"), g.edges.join(ids, "parent", "left_anti")).cut()
    found = maintain.append_nodes(old, cut(partition.forward_partition(old)), late, g.edges.join(ids, "parent", "left_semi"))
    return maintain.renamed(found)


def _changes(g) -> tuple[DataFrame, DataFrame]:
    """Edges to insert, from nodes to children of their children, and edges to delete."""
    below = g.edges.select(F.col("parent").alias("via"), F.col("child").alias("to"))
    inserted = g.edges.where("parent % 499 = 7").join(below, F.col("child") == F.col("via")).select("parent", F.col("to").alias("child")).distinct()
    return cut(inserted), cut(g.edges.where("(parent + child) % 1009 = 0"))


_nodes_sql, _edges_sql = O.ctes("reference").removeprefix("WITH RECURSIVE ").rsplit(", e AS (", 1)
_changed_sql = f"WITH RECURSIVE {_nodes_sql}, e0 AS ({_edges_sql}, e AS (SELECT parent, child FROM e0 WHERE (parent + child) % 1009 <> 0 UNION SELECT a.parent, b.child FROM e0 a JOIN e0 b ON b.parent = a.child WHERE a.parent % 499 = 7)"
add("append_nodes_orders", _append_orders, O.forward(O.ctes("reference"), ROUNDS["reference"]))
add("edge_changes", _graph("reference", lambda g: maintain.edge_changes(g, cut(partition.forward_partition(g)), *_changes(g))), O.forward(_changed_sql, ROUNDS["reference"]))
add("edge_changes_recomputed", _graph("reference", lambda g: maintain.recompute(g, *_changes(g)).select("node_id", "block_id")), O.forward(_changed_sql, ROUNDS["reference"]))

# --- generators and operators around them --------------------------------------------------------------------------
def _parts(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part").select(F.col("p_partkey").cast("long").alias("id"))


def _tree_of_parts(spark: SparkSession, d: str) -> DataFrame:
    ids = _parts(spark, d)
    t = generate.random_tree(spark, (ids.agg(F.max("id")).first()[0] or 0) + 1, ids=ids)
    return t.select("node_id", F.coalesce("parent", F.lit(-1)).cast("long").alias("parent"), F.col("depth").cast("long").alias("depth"))


add("dense_dag_edges", lambda spark, d: generate.dense_groups(load(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("id"), F.col("s_nationkey").alias("part")), 10), "SELECT CAST(p.s_suppkey AS BIGINT) AS parent, CAST(c.s_suppkey AS BIGINT) AS child FROM supplier p JOIN supplier c ON c.s_nationkey = p.s_nationkey AND c.s_suppkey < p.s_suppkey WHERE (p.s_suppkey * 7919 + c.s_suppkey * 104729) % 1000 < 100")
_mix = lambda *v: "((" + __import__("functools").reduce(lambda x, y: f"((({x} + {y}) % 2147483648) * 1103515245 + 12345) % 2147483648", v, "0::BIGINT") + " * 1103515245 + 12345) % 2147483648) // 16"
add("random_dag_edges", lambda spark, d: generate.random_dag(spark, 0, ids=_parts(spark, d)).edges, f"SELECT DISTINCT parent, {_mix('1', 'parent', 'k')} % parent AS child FROM (SELECT CAST(p_partkey AS BIGINT) AS parent FROM part WHERE p_partkey > 0), range(1, 5) y(k)")
_starts = ", ".join(str((3**k - 1) // 2) for k in range(1, 39))  # the first node of each level but the root's
add("random_tree", _tree_of_parts, f"SELECT CAST(p_partkey AS BIGINT) AS node_id, CAST(CASE WHEN p_partkey > 0 THEN (p_partkey - 1) // 3 ELSE -1 END AS BIGINT) AS parent, CAST(len(list_filter([{_starts}], lambda x: x <= p_partkey)) AS BIGINT) AS depth FROM part")
add("semi_roots", _graph("reference", lambda g: __import__("dagquotient.operators.graph", fromlist=["roots"]).roots(g).select("node_id")), f"{O.ctes('reference')} SELECT node_id FROM n WHERE node_id NOT IN (SELECT child FROM e)")
add("anti_leaves", _graph("reference", lambda g: __import__("dagquotient.operators.graph", fromlist=["leaves"]).leaves(g).select("node_id")), f"{O.ctes('reference')} SELECT node_id FROM n WHERE node_id NOT IN (SELECT parent FROM e)")
add("tumbling_events", lambda spark, d: load(spark, d, "events").groupBy(F.date_trunc("day", "ts").cast("date").alias("day"), "event_type").agg(F.count("*").alias("n")), "SELECT ts::DATE AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
add("rollup_labels", lambda spark, d: fixtures.graph(spark, d, "reference").nodes.rollup(F.floor(F.col("node_id") / 10**14).alias("kind"), "label").agg(F.count("*").alias("n")), f"{O.ctes('reference')} SELECT node_id // 100000000000000 AS kind, label, count(*) AS n FROM n GROUP BY ROLLUP (kind, label)")
add("top_blocks_reference", _graph("reference", lambda g: _index(partition.forward_partition)(g).blocks.select("block_id", "label", "n_members", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("n_members"), "block_id")).cast("long").alias("place")).where("place <= 3")), O.quotient_nodes(O.forward(O.ctes("reference"), 5)).replace("GROUP BY block_id", "GROUP BY block_id QUALIFY row_number() OVER (PARTITION BY min(label) ORDER BY count(*) DESC, block_id) <= 3").replace("count(*) AS n_members FROM", "count(*) AS n_members, row_number() OVER (PARTITION BY min(label) ORDER BY count(*) DESC, block_id) AS place FROM"))


from dagquotient import surface, workloads  # noqa: E402

for _name, (_query, _sql) in surface.QUERIES.items():
    add(_name, _query, _sql)
for _name, _query in workloads.QUERIES.items():  # seconds and bytes as they are measured: no SQL
    add(_name, _query)


def _document_blocks(spark: SparkSession, d: str) -> DataFrame:
    p = partition.forward_partition(fixtures.document_words(spark, d).cut())
    return p.where("node_id % 4 = 0").select(F.expr("node_id div 4").alias("node_id"), F.expr("block_id div 4").alias("block_id"))


add("forward_documents", _document_blocks, O.DOCUMENT_WORDS)
add("degrees_random", _graph("random", graph.degrees), f"{O.ctes('random')} SELECT node_id, coalesce(c, 0) AS children, coalesce(p, 0) AS parents FROM n LEFT JOIN (SELECT parent AS node_id, count(*) AS c FROM e GROUP BY 1) USING (node_id) LEFT JOIN (SELECT child AS node_id, count(*) AS p FROM e GROUP BY 1) USING (node_id)")


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_oracles)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of the containment graph and their sizes."""
    return _index(partition.forward_partition)(fixtures.graph(spark, sf_dir, "containment").cut()).blocks


__all__ = ["flagship", "oracle_sql", "queries", "sql_over"]
