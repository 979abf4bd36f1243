"""Structured Streaming over event files: windowed counts, A(k) traces of each user's chain of events, late events,
edges between events that are near in time, edges told more than once.

Every query runs over what files there are (``availableNow``) and resumes from its checkpoint. Checkpoints and results
lie in the folder that executors share.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import BooleanType, StructField, StructType

from dagquotient.functions.lineage import fresh_path
from dagquotient.operators import maintain
from dagquotient.operators.graph import LabeledDag
from dagquotient.operators.tree import PAD

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(SCHEMA).parquet(path)


def counted(events: DataFrame, window: Column, *keys: str) -> DataFrame:
    """``window`` (start and end), ``keys``, n: a table that is written anew with each batch, counts are its state."""
    spark = events.sparkSession
    out = fresh_path(spark, "counts")
    counts = events.groupBy(window.alias("window"), *keys).agg(F.count("*").alias("n"))
    writer = counts.writeStream.outputMode("complete").option("checkpointLocation", fresh_path(spark, "state"))
    writer.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(counts.schema).parquet(out)


def traces(events: DataFrame, k: int) -> DataFrame:
    """node_id, trace: of every event the labels of the ``k`` events of its user before it, and its own.

    The state of a user is the last ``k`` labels. Events of a batch are put in order of time; one that comes in a later
    batch than a younger one follows it.
    """

    def run(_: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0].split("/") if state.exists else [PAD] * k
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        out = []
        for label in rows["event_type"]:
            last = [*last, label]
            out.append("/".join(last[-(k + 1) :]))
            last = last[1:]
        state.update(("/".join(last),))
        yield pd.DataFrame({"node_id": rows["event_id"], "trace": out})

    if k < 1:
        raise ValueError("k must be 1 or more")
    spark, schema = events.sparkSession, "node_id long, trace string"
    out = fresh_path(spark, "traces")
    found = events.select("event_id", "ts", "user_id", "event_type").groupBy("user_id").applyInPandasWithState(run, schema, "last string", "append", GroupStateTimeout.NoTimeout)
    found.writeStream.format("parquet").option("checkpointLocation", fresh_path(spark, "state")).option("path", out).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema).parquet(out)


def _appended(found: DataFrame, what: str) -> DataFrame:
    """The rows of a stream that only adds some, as a table."""
    spark = found.sparkSession
    out = fresh_path(spark, what)
    found.writeStream.format("parquet").option("checkpointLocation", fresh_path(spark, "state")).option("path", out).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(found.schema).parquet(out)


def _instant(ts: str) -> Column:
    """The instant at which clocks in UTC show ``ts``: watermarks need one."""
    return F.convert_timezone(F.lit("UTC"), F.current_timezone(), F.col(ts)).cast("timestamp")


def closed_windows(events: DataFrame, length: str, delay: str, *keys: str) -> DataFrame:
    """window, ``keys``, n of the windows that the watermark has passed.

    An event behind the watermark that the batch before began with is not counted any more.
    """
    counts = events.withColumn("ts", _instant("ts")).withWatermark("ts", delay).groupBy(F.window("ts", length).alias("window"), *keys).agg(F.count("*").alias("n"))
    return _appended(counts, "closed")


def by_punctuality(events: DataFrame, delay: str) -> tuple[DataFrame, DataFrame]:
    """(on time, late) events: late is what lies more than ``delay`` behind the youngest event of earlier batches.

    Late ones are kept apart for a later edge change. A batch that is run again writes the same folders again.
    """
    spark, at = events.sparkSession, fresh_path(events.sparkSession, "punctual")
    dealt_fields = StructType([*events.schema.fields, StructField("late", BooleanType())])
    spark.createDataFrame([], dealt_fields).write.parquet(f"{at}/events/none")
    spark.createDataFrame([], "youngest timestamp_ntz, batch long").write.parquet(f"{at}/youngest/none")

    def deal(df: DataFrame, batch: int) -> None:
        marks = spark.read.schema("youngest timestamp_ntz, batch long").option("recursiveFileLookup", "true").parquet(f"{at}/youngest")
        mark = F.broadcast(marks.where(F.col("batch") < batch).agg(F.max("youngest").alias("mark")))  # one row
        told = df.join(mark).withColumn("late", F.coalesce(F.col("ts") < F.col("mark") - F.expr(f"INTERVAL {delay}"), F.lit(False)))
        told.drop("mark").write.mode("overwrite").parquet(f"{at}/events/{batch}")
        df.agg(F.max("ts").alias("youngest"), F.lit(batch).cast("long").alias("batch")).write.mode("overwrite").parquet(f"{at}/youngest/{batch}")

    writer = events.writeStream.option("checkpointLocation", fresh_path(spark, "state")).foreachBatch(deal)
    writer.trigger(availableNow=True).start().awaitTermination()

    dealt = spark.read.schema(dealt_fields).option("recursiveFileLookup", "true").parquet(f"{at}/events")
    return dealt.where("NOT late").drop("late"), dealt.where("late").drop("late")


def near_edges(first: DataFrame, then: DataFrame, kinds: tuple[str, str], within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """parent, child: an event of the second kind and one of the first of the same user, at most ``within`` before it.

    Both streams are kept only as long as the watermarks allow a partner.
    """
    a = first.where(F.col("event_type") == kinds[0]).select(F.col("event_id").alias("child"), F.col("user_id").alias("who"), _instant("ts").alias("seen")).withWatermark("seen", delay)
    b = then.where(F.col("event_type") == kinds[1]).select(F.col("event_id").alias("parent"), "user_id", _instant("ts").alias("done")).withWatermark("done", delay)
    near = F.expr(f"user_id = who AND seen <= done AND seen >= done - INTERVAL {within}")
    return _appended(b.join(a, near).select("parent", "child"), "edges")


def edges_once(edges: DataFrame, delay: str = "1 day") -> DataFrame:
    """parent, child, ts of a stream of edges, without repetitions that come within ``delay`` of the first one."""
    return _appended(edges.withColumn("ts", _instant("ts")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["parent", "child"]), "once")


def indexed(arrivals: DataFrame) -> DataFrame:
    """node_id, block_id of a stream of node_id, label, children, in which children come no later than their parents.

    Each batch is appended to the partition of what came before; blocks keep their names. A batch that is run again
    reads earlier batches only, and overwrites its own folders.
    """
    spark = arrivals.sparkSession
    at = fresh_path(spark, "indexed")
    kinds = {"nodes": "node_id long, label string", "edges": "parent long, child long", "blocks": "node_id long, block_id long"}

    def read(kind: str, batches: range) -> DataFrame:
        paths = [f"{at}/{kind}/{k}" for k in batches]
        return spark.read.schema(kinds[kind]).parquet(*paths) if paths else spark.createDataFrame([], kinds[kind])

    done = [0]

    def grow(df: DataFrame, batch: int) -> None:
        df.select("node_id", "label").write.mode("overwrite").parquet(f"{at}/nodes/{batch}")
        df.select(F.col("node_id").alias("parent"), F.explode("children").alias("child")).distinct().write.mode("overwrite").parquet(f"{at}/edges/{batch}")
        before, now = range(batch), range(batch, batch + 1)
        nodes = read("nodes", now)
        grown = maintain.append_nodes(LabeledDag(read("nodes", before), read("edges", before)), read("blocks", before), nodes, read("edges", now))
        grown.join(nodes.select("node_id"), "node_id", "left_semi").write.mode("overwrite").parquet(f"{at}/blocks/{batch}")
        done[0] = batch + 1

    writer = arrivals.writeStream.option("checkpointLocation", fresh_path(spark, "state")).foreachBatch(grow)
    writer.trigger(availableNow=True).start().awaitTermination()
    return read("blocks", range(done[0]))
