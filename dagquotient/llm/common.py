"""What several operators share: table access, lineage cuts in the shared folder, size-checked broadcasts."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager, suppress
from weakref import WeakKeyDictionary

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: A broadcast side may hold this many rows at most; beyond it the join is left to shuffles.
BROADCAST_ROWS = 1_000_000
#: Bits that the bitmap of a sieve has at most (32 MB), and bits of a row of it.
SIEVE_BITS, _BUCKET = 1 << 28, 1 << 15
#: Ends the life of shuffle files with the statement that made them; the session's own value is put back.
_FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_cuts: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()
_told: WeakKeyDictionary[DataFrame, dict[str, int]] = WeakKeyDictionary()


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named parquet table of ``sf_dir``, with only ``columns`` read."""
    df = spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Only a local session that names none gets a temporary one."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        at = f"{tempfile.gettempdir()}/checkpoints"
        spark.conf.set("spark.checkpoint.dir", at)
    return at.rstrip("/")


@contextmanager
def freed(spark: SparkSession) -> Iterator[None]:
    """Statements in here leave no shuffle files behind."""
    before = spark.conf.get(_FREED)
    spark.conf.set(_FREED, "true")
    try:
        yield
    finally:
        spark.conf.set(_FREED, before)


def cut(df: DataFrame, **sums: Column) -> DataFrame:
    """``df`` written as a table to the shared folder and read again: its lineage ends there.

    The tasks that write it count its rows, and take the aggregates ``sums``; ``told`` gives them without a job.
    """
    at = f"{shared_dir(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    seen = Observation()
    with freed(df.sparkSession):
        df.observe(seen, F.count(F.lit(1)).alias("rows"), *[c.alias(name) for name, c in sums.items()]).write.parquet(at)
    out = df.sparkSession.read.schema(df.schema).parquet(at)
    _cuts[out], _told[out] = at, seen.get
    return out


def told(df: DataFrame, name: str = "rows") -> int | None:
    """The number of rows of a table that ``cut`` wrote, or another of the aggregates that it was asked for."""
    return _told[df][name]


def drop(*cuts: DataFrame) -> None:
    """Deletes the tables of ``cut`` that no result is read from any more."""
    for df in cuts:
        if at := _cuts.pop(df, None):
            spark = df.sparkSession
            path = spark._jvm.org.apache.hadoop.fs.Path(at)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def small(df: DataFrame, rows: int, most: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` marked for broadcast if its measured row count allows that, else as it is."""
    return F.broadcast(df) if rows <= most else df


def sieve(keys: DataFrame, rows: int, *key: str) -> Callable[[DataFrame], DataFrame]:
    """What adds a column ``may`` to a table: true where ``key`` is one of ``keys``, and of about one in 16 others.

    ``rows``, the measured count of ``keys``, gives the size of the bitmap that is broadcast: 2 bytes a key, ``SIEVE_BITS`` at
    most. From there on more of the others pass.
    """
    bits = min(SIEVE_BITS, max(_BUCKET, 1 << (16 * rows - 1).bit_length() if rows else 0))
    place = F.pmod(F.xxhash64(*key), F.lit(bits))
    bucket, at = F.floor(place / _BUCKET).cast("long"), F.pmod(place, F.lit(_BUCKET)).cast("long")
    maps = cut(keys.select(bucket.alias("_bucket"), at.alias("_at")).distinct().repartition("_bucket").groupBy("_bucket").agg(F.bitmap_construct_agg("_at").alias("_map")))

    def mark(df: DataFrame) -> DataFrame:
        both = df.withColumns({"_bucket": bucket, "_at": at}).join(F.broadcast(maps), "_bucket", "left")
        byte = F.conv(F.hex(F.substring("_map", (F.floor(F.col("_at") / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
        return both.withColumn("may", F.coalesce(F.getbit(byte, F.pmod("_at", F.lit(8)).cast("int")) == 1, F.lit(False))).drop("_bucket", "_at", "_map")

    return mark


def among(df: DataFrame, keys: DataFrame, rows: int, *key: str, most: int | None = None) -> DataFrame:
    """``df`` joined by ``key`` with ``keys``: by a broadcast, or where ``rows`` forbids that by a shuffle of what a sieve leaves."""
    most = BROADCAST_ROWS if most is None else most
    if rows > most:
        df = sieve(keys, rows, *key)(df).where("may").drop("may")
    return df.join(small(keys, rows, most), list(key))


def without(df: DataFrame, keys: DataFrame, rows: int, *key: str, most: int | None = None) -> DataFrame:
    """The rows of ``df`` whose ``key``, never null, isn't one of ``keys``; where ``rows`` forbids a broadcast only what a sieve marks is shuffled."""
    most = BROADCAST_ROWS if most is None else most
    if rows <= most:
        return df.join(small(keys, rows, most), list(key), "left_anti")
    marked = sieve(keys, rows, *key)(df)
    clear, rest = (marked.where(c).drop("may") for c in (~F.col("may"), F.col("may")))
    return clear.unionByName(rest.join(keys, list(key), "left_anti"))


def trim() -> None:
    """Gives back what this worker process has freed: it outlives its tasks, and later stages run beside it."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # not glibc
        ctypes.CDLL(None).malloc_trim(0)


def trimmed(run):
    """``run`` over batches, after which the worker gives back what it has freed."""

    def both(batches):
        trim()
        yield from run(batches)
        trim()

    return both


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` evaluated once, also where a lambda refers to it again and again."""
    return F.transform(F.array(value), body)[0]


def width(spark: SparkSession) -> int:
    """The number of shuffle partitions of this session."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def packed(docs: DataFrame, *more: Column) -> DataFrame:
    """``row``, all columns of ``docs`` in one, and columns ``more``, whose names then meet no name of ``docs``."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), *more)
