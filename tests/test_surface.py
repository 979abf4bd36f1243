"""Generators, ids of large documents, and streams against plain Python."""

import datetime as dt

import pytest
from pyspark.errors import SparkRuntimeException

from dagquotient.operators import tree
from dagquotient.sources import generate
from dagquotient.streaming import events as stream


@pytest.mark.parametrize("fanout", [1, 2, 3, 7])
def test_tree_depths(spark, fanout):
    got = {r["node_id"]: (r["parent"], r["depth"]) for r in generate.random_tree(spark, 200, fanout).collect()}
    depth = {0: 0}
    for i in range(1, 200):
        depth[i] = depth[(i - 1) // fanout] + 1
        assert got[i] == ((i - 1) // fanout, depth[i])
    assert got[0] == (None, 0)


def test_large_documents_never_share_ids(spark):
    pages = spark.createDataFrame([(k, "<p>" * 12) for k in range(3)], "page_id long, html string")
    stream_ = tree.tags(pages)
    assert tree.tree_of(stream_, stride=12).select("node_id").distinct().count() == 36
    with pytest.raises(SparkRuntimeException, match="more than 10 elements"):
        tree.tree_of(stream_, stride=10).collect()


def test_traces_go_on_from_batch_to_batch(spark, tmp_path):
    rows = [(k, dt.datetime(2024, 1, 1 + k // 10, k % 10), k % 3, "abc"[k % 7 % 3], 0.0, "{}") for k in range(60)]
    for part in range(3):
        spark.createDataFrame(rows[20 * part : 20 * part + 20], stream.SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    events = spark.readStream.schema(stream.SCHEMA).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = {r["node_id"]: r["trace"] for r in stream.traces(events, 2).collect()}
    want, last = {}, {}
    for i, _, user, label, *_ in rows:
        last[user] = [*last.get(user, ["#", "#"]), label][-3:]
        want[i] = "/".join(["#"] * (3 - len(last[user])) + last[user])
    assert got == want
    with pytest.raises(ValueError):
        stream.traces(events, 0)
