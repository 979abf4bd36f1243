"""Graphs on the test tables. Their definitions are SQL that Spark and DuckDB read alike: ``{name}`` is a table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagquotient.functions.lineage import cut, small
from dagquotient.operators import tree
from dagquotient.operators.graph import LabeledDag
from dagquotient.sources.tables import load, sql_over

_KIND = 10**14
_LINES = """(SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS nth FROM {lineitem})"""
_LINE_ID = "CAST(l_orderkey * 1000 + nth AS BIGINT)"


def _id(kind: int, key: str) -> str:
    return f"CAST({kind * _KIND} + {key} AS BIGINT)"


def _nodes(*parts: tuple[int, str, str, str]) -> str:
    return " UNION ALL ".join(f"SELECT {_id(kind, key)} AS node_id, {label} AS label FROM {table}" for kind, key, label, table in parts)


def _edges(*parts: tuple[int, str, int, str, str]) -> str:
    return " UNION ".join(f"SELECT {_id(a, x)} AS parent, {_id(b, y)} AS child FROM {table}" for a, x, b, y, table in parts)


CONTAINMENT = (
    _nodes((5, "r_regionkey", "'region'", "{region}"), (4, "n_nationkey", "'nation'", "{nation}"), (3, "c_custkey", "concat('cust:', c_mktsegment)", "{customer}"), (2, "o_orderkey", "concat('ord:', o_orderstatus)", "{orders}"), (1, _LINE_ID, "concat('li:', l_returnflag, l_linestatus)", f"{_LINES} l")),
    _edges((5, "n_regionkey", 4, "n_nationkey", "{nation}"), (4, "c_nationkey", 3, "c_custkey", "{customer}"), (3, "o_custkey", 2, "o_orderkey", "{orders}"), (2, "l_orderkey", 1, _LINE_ID, f"{_LINES} l")),
)
REFERENCE = (
    _nodes((1, "r_regionkey", "concat('region:', r_name)", "{region}"), (2, "n_nationkey", "'nation'", "{nation}"), (3, "p_partkey", "concat('part:', p_type)", "{part}"), (4, "s_suppkey", "'supp'", "{supplier}"), (5, "c_custkey", "concat('cust:', c_mktsegment)", "{customer}"), (6, "o_orderkey", "concat('ord:', o_orderstatus)", "{orders}"), (7, _LINE_ID, "concat('li:', l_returnflag)", f"{_LINES} l")),
    _edges((2, "n_nationkey", 1, "n_regionkey", "{nation}"), (4, "s_suppkey", 2, "s_nationkey", "{supplier}"), (5, "c_custkey", 2, "c_nationkey", "{customer}"), (6, "o_orderkey", 5, "o_custkey", "{orders}"), (7, _LINE_ID, 6, "l_orderkey", f"{_LINES} l"), (7, _LINE_ID, 3, "l_partkey", f"{_LINES} l"), (7, _LINE_ID, 4, "l_suppkey", f"{_LINES} l")),
)
_ENDS = "(SELECT l_orderkey AS a, (l_partkey * 7919 + l_suppkey * 104729 + l_linenumber * 31 + CAST(l_quantity AS BIGINT) * 1299709) % (SELECT count(*) FROM {orders}) AS b FROM {lineitem}) x"
RANDOM = (
    "SELECT o_orderkey AS node_id, o_orderstatus AS label FROM {orders}",
    f"SELECT DISTINCT greatest(a, b) AS parent, least(a, b) AS child FROM {_ENDS} WHERE a <> b",
)
TWO_TIER = (
    RANDOM[0],
    "SELECT DISTINCT greatest(l_orderkey, l_partkey) AS parent, least(l_orderkey, l_partkey) AS child FROM {lineitem} WHERE l_orderkey <> l_partkey",
)
EVENT_CHAIN = (
    "SELECT event_id AS node_id, event_type AS label FROM {events}",
    "SELECT event_id AS parent, child FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts) AS child FROM {events}) x WHERE child IS NOT NULL",
)
CONVERSATION = (
    "SELECT conv_id * 1000 + turn AS node_id, role AS label FROM {conversations}",
    "SELECT conv_id * 1000 + turn AS parent, conv_id * 1000 + nxt AS child FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM {conversations}) x WHERE nxt IS NOT NULL",
)
EVENT_SESSION = (
    EVENT_CHAIN[0],
    "SELECT event_id AS parent, child FROM (SELECT event_id, ts, lead(event_id) OVER w AS child, lead(ts) OVER w AS nxt FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts)) x WHERE nxt <= ts + INTERVAL '6' HOUR",
)
#: Documents, the pairs of source and language that they are from, and languages.
_SOURCES = "(SELECT DISTINCT source, lang FROM {documents})"
DOCUMENT_SOURCES = (
    "SELECT doc_id + 1000000000 AS node_id, 'doc' AS label FROM {documents} UNION ALL SELECT CAST(1000 + dense_rank() OVER (ORDER BY source, lang) AS BIGINT), concat('in:', lang) FROM " + _SOURCES + " x UNION ALL SELECT DISTINCT CAST(ascii(lang) * 256 + ascii(substr(lang, 2, 1)) - 30000 AS BIGINT), concat('w:', lang) FROM {documents}",
    "SELECT doc_id + 1000000000 AS parent, k AS child FROM {documents} d JOIN (SELECT source, lang, CAST(1000 + dense_rank() OVER (ORDER BY source, lang) AS BIGINT) AS k FROM " + _SOURCES + " y) x ON d.source = x.source AND d.lang = x.lang UNION SELECT CAST(1000 + dense_rank() OVER (ORDER BY source, lang) AS BIGINT), CAST(ascii(lang) * 256 + ascii(substr(lang, 2, 1)) - 30000 AS BIGINT) FROM " + _SOURCES + " z",
)


def dense(percent: int) -> tuple[str, str]:
    return (
        "SELECT s_suppkey AS node_id, concat('n', CAST(s_nationkey % 5 AS VARCHAR(2))) AS label FROM {supplier}",
        f"SELECT p.s_suppkey AS parent, c.s_suppkey AS child FROM {{supplier}} p JOIN {{supplier}} c ON p.s_suppkey > c.s_suppkey WHERE (p.s_suppkey * 7919 + c.s_suppkey * 104729) % 1000 < {10 * percent}",
    )


GRAPHS = {"containment": CONTAINMENT, "reference": REFERENCE, "random": RANDOM, "two_tier": TWO_TIER, "event_chain": EVENT_CHAIN, "conversation": CONVERSATION, "event_session": EVENT_SESSION, "document_sources": DOCUMENT_SOURCES, "dense0": dense(0), "dense1": dense(1), "dense10": dense(10), "dense50": dense(50), "dense100": dense(100)}


def graph(spark: SparkSession, sf_dir: str, name: str) -> LabeledDag:
    if name == "pages":
        return tree.graph_of(page_trees(spark, sf_dir))
    nodes, edges = GRAPHS[name]
    if name.startswith("dense"):
        return _dense_graph(spark, sf_dir, nodes, edges)
    return LabeledDag.of(sql_over(spark, sf_dir, nodes), sql_over(spark, sf_dir, edges))


def _dense_graph(spark: SparkSession, sf_dir: str, nodes: str, edges: str) -> LabeledDag:
    """The pairs of distinct keys are a set as they are; keys are dealt out, as a task forms the pairs of its own ones with all."""
    keys = cut(load(spark, sf_dir, "supplier").select("s_suppkey").distinct())
    many = keys.count()
    dealt = keys.repartition(max(1, min(many // 100, 4 * spark.sparkContext.defaultParallelism)), "s_suppkey")
    text = edges.replace("{supplier} p", "{keys} p").replace("{supplier} c", "{dealt} c")
    pairs = spark.sql(text, dealt=dealt, keys=small(keys, many))
    long = pairs.select(F.col("parent").cast("long").alias("parent"), F.col("child").cast("long").alias("child"))
    return LabeledDag(LabeledDag.of(sql_over(spark, sf_dir, nodes), long).nodes, long)


def document_words(spark: SparkSession, sf_dir: str) -> LabeledDag:
    """Documents, their distinct lines and the distinct words of these, numbered without a window over all texts.

    Documents are node doc_id * 4; ids of lines and words (remainders 1 and 2) hold for this graph only.
    """
    docs = load(spark, sf_dir, "documents")
    in_doc = docs.select((F.col("doc_id") * 4).alias("doc"), F.explode(F.split("text", "\n")).alias("line")).distinct()
    in_doc = cut(in_doc)
    lines = cut(in_doc.select("line").distinct().withColumn("line_id", F.monotonically_increasing_id() * 4 + 1))
    in_line = cut(lines.select("line_id", F.explode(F.split("line", r"[ \t\r\f\x0b]+")).alias("word")).where("word <> ''").distinct())
    words = cut(in_line.select("word").distinct().withColumn("word_id", F.monotonically_increasing_id() * 4 + 2))
    nodes = docs.select((F.col("doc_id") * 4).alias("node_id"), F.lit("doc").alias("label")).distinct()
    nodes = nodes.unionByName(lines.select(F.col("line_id").alias("node_id"), F.lit("line").alias("label")))
    nodes = nodes.unionByName(words.select(F.col("word_id").alias("node_id"), F.concat(F.lit("w:"), "word").alias("label")))
    edges = in_doc.join(lines, "line").select(F.col("doc").alias("parent"), F.col("line_id").alias("child"))
    return LabeledDag(nodes, edges.unionByName(in_line.join(words, "word").select(F.col("line_id").alias("parent"), F.col("word_id").alias("child"))))


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree.tags(load(spark, sf_dir, "pages").select("page_id", "html"))


def page_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree.tree_of(page_tags(spark, sf_dir))


def containment_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The containment graph as a tree table: depth is told by the kind of row."""
    g = graph(spark, sf_dir, "containment")
    up = g.edges.select(F.col("child").alias("node_id"), "parent")
    return g.nodes.join(up, "node_id", "left").select("node_id", "parent", (5 - F.floor(F.col("node_id") / _KIND)).cast("int").alias("depth"), "label", F.lit(0).cast("long").alias("doc_id"))


#: The two worked examples: fixed values. Nodes as (id, label), edges as (parent, child).
PAIR_LEFT = ([(1, "a"), (2, "b"), (3, "b"), (4, "c"), (5, "c"), (9, "d"), (10, "d")], [(1, 2), (1, 3), (2, 4), (2, 5), (3, 4), (9, 3), (10, 4)])
PAIR_RIGHT = ([(6, "a"), (7, "b"), (8, "c"), (11, "d"), (12, "d")], [(6, 7), (7, 8), (11, 7), (12, 8)])
TREE = ([(0, "a"), (1, "a"), (2, "a"), (3, "b"), (4, "c"), (5, "b"), (6, "c"), (7, "a"), (8, "b"), (9, "c")], [(0, 1), (0, 2), (1, 3), (1, 4), (2, 5), (2, 6), (2, 7), (7, 8), (7, 9)])


def literal(spark: SparkSession, *parts: tuple[list, list]) -> LabeledDag:
    nodes, edges = [n for p in parts for n in p[0]], [e for p in parts for e in p[1]]
    return LabeledDag(spark.createDataFrame(nodes, "node_id long, label string"), spark.createDataFrame(edges, "parent long, child long"))


def literal_copies(spark: SparkSession, sf_dir: str, *parts: tuple[list, list]) -> LabeledDag:
    """A copy of the worked example for each supplier, its labels marked by the supplier's nation."""
    one = literal(spark, *parts)
    suppliers = load(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 16).alias("first"), F.col("s_nationkey").cast("string").alias("nation"))
    nodes = suppliers.crossJoin(F.broadcast(one.nodes)).select((F.col("first") + F.col("node_id")).alias("node_id"), F.concat_ws(":", "label", "nation").alias("label"))
    edges = suppliers.crossJoin(F.broadcast(one.edges)).select((F.col("first") + F.col("parent")).alias("parent"), (F.col("first") + F.col("child")).alias("child"))
    return LabeledDag.of(nodes, edges).cut()
