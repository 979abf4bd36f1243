"""Measured runs, documents in chunks, layouts, and streams that add edges, nodes and late events."""

import datetime as dt

import pytest

from dagquotient import workloads
from dagquotient.functions.lineage import cut
from dagquotient.operators import graph, partition, ranks, tree
from dagquotient.operators.maintain import renamed
from dagquotient.sources import fixtures
from dagquotient.streaming import events as stream

SMALL = "/root/testdata/sf0.001"


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("chunk", [1, 3, 1000])
def test_levels_in_chunks(spark, chunk):
    pages = spark.createDataFrame([(0, "<a><a><b/><c></c></a><a><b></b><p><i></i></p></a></a><q></q>"), (1, ""), (2, None), (3, "<p>" * 9)], "page_id long, html string")
    stream_ = cut(tree.tags(pages))
    for a, b in zip(tree.levels(stream_), tree.levels_in_chunks(stream_, chunk), strict=True):
        assert rows(a.select(sorted(a.columns))) == rows(b.select(sorted(a.columns)))


def test_documents_lines_words(spark):
    assert fixtures.document_words(spark, SMALL).size() == (29_533, 63_337)


def test_layouts_and_views(spark):
    g = fixtures.literal(spark, fixtures.PAIR_LEFT)
    ranked = cut(ranks.by_peeling(g))
    assert rows(partition.nodes_by_rank(ranked).where("rank = 0").select("node_id")) == [(4,), (5,)]
    assert rows(partition.edges_by_rank(g, ranked).where("child_rank = 1")) == [(1, 2, 2, 1), (1, 3, 2, 1), (9, 3, 2, 1)]
    start = spark.createDataFrame([(3,), (3,)], "node_id long")
    assert rows(graph.children_of(g, start)) == [(3, 4)]
    assert rows(graph.parents_of(g, start).select("parent", "child")) == [(1, 3), (9, 3)]


def test_less_memory_costs_more(spark):
    g = fixtures.literal(spark, fixtures.TREE)
    got = workloads.memory(spark, g, (1.0, 0.0)).table().collect()
    assert [r["items"] for r in got] == [19, 19]
    assert 0 < got[0]["bytes_read"] < got[1]["bytes_read"] and got[0]["stages"] < got[1]["stages"]
    assert all(r["transfers_per_item"] == r["transfers"] / 19 and r["bytes_written"] > 0 for r in got)


def test_shares_of_a_graph_larger_than_a_task(spark, monkeypatch):
    asked, peel = [], ranks.by_peeling
    monkeypatch.setattr(ranks, "FUSE_ROWS", 10)
    monkeypatch.setattr(ranks, "by_peeling", lambda g, fuse_rows: asked.append(fuse_rows) or peel(g, fuse_rows=fuse_rows))
    assert len(workloads.memory(spark, fixtures.literal(spark, fixtures.TREE), (1.0, 0.5)).table().collect()) == 2
    assert asked == [10, 5]


def test_recursive_ranks_beyond_the_row_limit(spark):
    spark.conf.set("spark.sql.cteRecursionRowLimit", "8")
    try:
        got = rows(ranks.by_recursive_sql(fixtures.literal(spark, fixtures.PAIR_LEFT)).select("node_id", "rank"))
        assert got == [(1, 2), (2, 1), (3, 1), (4, 0), (5, 0), (9, 2), (10, 1)] and spark.conf.get("spark.sql.cteRecursionRowLimit") == "8"
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")


def files(spark, path, *parts, schema):
    for k, part in enumerate(parts):
        spark.createDataFrame(part, schema).coalesce(1).write.parquet(f"{path}/{k}")
    return spark.readStream.schema(schema).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(str(path))


def event(k, hour, kind="view", user=1):
    return (k, dt.datetime(2024, 1, 1) + dt.timedelta(hours=hour), user, kind, 0.0, "{}")


def test_late_events_are_kept_apart(spark, tmp_path):
    events = files(spark, tmp_path / "in", [event(1, 10), event(2, 0)], [event(3, 8.5), event(4, 9.5), event(5, 20)], [event(6, 18), event(7, 19.5)], schema=stream.SCHEMA)
    on_time, late = (rows(df.select("event_id")) for df in stream.by_punctuality(events, "1 HOUR"))
    assert (on_time, late) == ([(1,), (2,), (4,), (5,), (7,)], [(3,), (6,)])


def test_windows_close_behind_the_watermark(spark, tmp_path):
    events = files(spark, tmp_path / "in", [event(1, 0.2), event(2, 0.4)], [event(3, 10)], [event(5, 10.5)], [event(4, 0.5)], schema=stream.SCHEMA)
    got = stream.closed_windows(events, "1 hour", "1 hour", "user_id").select("user_id", "n")
    assert rows(got) == [(1, 2)]


def test_near_edges_and_edges_once(spark, tmp_path):
    kinds = [event(1, 0), event(2, 1, "purchase"), event(3, 0.5, "view", 2), event(4, 1.5), event(5, 2, "purchase"), event(6, 9, "purchase")]
    events = files(spark, tmp_path / "in", kinds[:3], kinds[3:], schema=stream.SCHEMA)
    assert rows(stream.near_edges(events, events, ("view", "purchase"))) == [(2, 1), (5, 4)]
    told = [(1, 2, dt.datetime(2024, 1, 1)), (1, 2, dt.datetime(2024, 1, 1, 1)), (1, 3, dt.datetime(2024, 1, 1))]
    again = files(spark, tmp_path / "edges", told, told[1:], schema="parent long, child long, ts timestamp_ntz")
    assert rows(stream.edges_once(again).select("parent", "child")) == [(1, 2), (1, 3)]


def test_stream_of_nodes(spark, tmp_path):
    schema = "node_id long, label string, children array<long>"
    first, then = [(1, "x", []), (2, "x", []), (3, "y", [1])], [(4, "y", [2]), (5, "z", [3, 4]), (6, "z", [4])]
    got = renamed(cut(stream.indexed(files(spark, tmp_path / "in", first, then, schema=schema))))
    assert rows(got.select("node_id", "block_id")) == [(1, 1), (2, 1), (3, 3), (4, 3), (5, 5), (6, 5)]


def test_generated_graphs_come_from_tables(spark):
    """Of each, as many rows as the table of SMALL makes, equal to the SQL over it."""
    import __spark_entry__ as entry
    import duckdb

    con = duckdb.connect()
    for t in ("supplier", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    for name in ("dense_dag_edges", "random_dag_edges", "random_tree", "example_pair_partition", "example_pair_quotient_edges", "example_tree_forward"):
        want = con.execute(entry.oracle_sql()[name]).fetchall()
        got = entry.queries()[name](spark, SMALL)
        assert rows(got) == sorted(want), name
        if name == "random_tree":
            assert len(want) == spark.read.parquet(f"{SMALL}/part.parquet").count()
