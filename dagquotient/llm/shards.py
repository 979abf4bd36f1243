"""Sharding by extendible hashing.

A directory is indexed by leading bits of a hash of each document. A bucket over the byte limit, and no other, is split
on another bit, until every shard fits; a shard is a (depth, prefix) pair. Eight bits are looked at in one pass over
the documents of oversized buckets: the sums of their cells are rolled up, and each bucket is split just as far as it
must be.

Rows that use up all bits together (alike in id and text) can't be parted by bits. Such a bucket gets overflow pages:
a row of more than half the limit has a page of its own, the others fill pages of half the limit and one row more. A
single row over the limit is a shard of its own. Null ids and null texts (of 0 bytes) are placed like others, an empty
table has no shards, extra columns are ignored by ``assign`` and kept by ``write``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.llm.common import cut, small

#: Hash bits that the directory may use, and bits that are looked at in one pass.
BITS, STEP = 56, 8


def placed(docs: DataFrame) -> DataFrame:
    """The columns of ``docs``, ``bytes`` and ``h``, the hash of ``BITS`` bits that places a document."""
    h = F.conv(F.substring(F.md5(F.concat_ws("|", F.col("doc_id").cast("string"), "text")), 1, BITS // 4), 16, 10).cast("long")
    return docs.withColumns({"bytes": F.coalesce(F.octet_length("text"), F.lit(0)).cast("long"), "h": h})


def _fits(limit: int) -> Column:
    return (F.col("bytes") <= limit) | (F.col("n") == 1)


def directory(rows: DataFrame, limit: int) -> DataFrame:
    """depth, prefix, bytes, n: the buckets of ``placed`` rows. Only one of ``BITS`` bits may hold rows over the limit."""
    rows = rows.select("bytes", "h")
    sums = (F.sum("bytes").alias("bytes"), F.count("*").alias("n"))
    level = cut(rows.groupBy(F.lit(0).alias("depth"), F.lit(0).cast("long").alias("prefix")).agg(*sums))
    done = level.where(_fits(limit))
    for at in range(0, BITS, STEP):
        over = level.where(~_fits(limit)).select(F.col("prefix").alias("parent"))
        n_over = over.count()
        if not n_over:
            return done
        inside = rows.withColumn("parent", F.shiftright("h", BITS - at)).join(small(over, n_over), "parent", "left_semi")
        cells = inside.groupBy("parent", F.shiftright("h", BITS - at - STEP).alias("cell")).agg(*sums)
        level = cut(_split(cells, at, limit))
        done = done.unionByName(level.where(_fits(limit)) if at + STEP < BITS else level)
    return done


def _split(cells: DataFrame, at: int, limit: int) -> DataFrame:
    """Of each cell of ``at + STEP`` bits, the bucket of least depth that fits, else the cell itself."""
    cells = cells.repartition("parent")  # all windows below keep to it
    pick = None
    for k in range(STEP, 0, -1):
        prefix = F.shiftright("cell", STEP - k)
        over = Window.partitionBy("parent", prefix)
        cells = cells.withColumns({f"bytes_{k}": F.sum("bytes").over(over), f"n_{k}": F.sum("n").over(over)})
        here = F.struct(F.lit(at + k).alias("depth"), prefix.alias("prefix"), F.col(f"bytes_{k}").alias("bytes"), F.col(f"n_{k}").alias("n"))
        pick = here if pick is None else F.when((F.col(f"bytes_{k}") <= limit) | (F.col(f"n_{k}") == 1), here).otherwise(pick)
    return cells.select(pick.alias("x")).select("x.*").distinct()


def assign(docs: DataFrame, limit: int) -> DataFrame:
    """doc_id, h, bytes, shard, shard_bytes: the shard of every row, named by depth, prefix and overflow page."""
    return _assigned(docs.select("doc_id", "text"), limit)


def _assigned(docs: DataFrame, limit: int, *more: str) -> DataFrame:
    """What ``assign`` gives, and the columns ``more`` of ``docs``."""
    rows = placed(docs).select("doc_id", "bytes", "h", *more)
    buckets = cut(directory(rows, limit)).withColumnRenamed("bytes", "bucket_bytes")
    known = buckets.groupBy("depth").count().collect()  # a row for each depth: BITS at most
    if not known:
        return rows.select("doc_id", "h", "bytes", F.lit("").alias("shard"), "bytes", *more).limit(0).toDF("doc_id", "h", "bytes", "shard", "shard_bytes", *more)
    at_depth = F.explode(F.array(*[F.struct(F.lit(r["depth"]).alias("depth"), F.shiftright("h", BITS - r["depth"]).alias("prefix")) for r in known]))
    rows = rows.select("*", at_depth.alias("x")).select("doc_id", "bytes", "h", "x.depth", "x.prefix", *more)
    found = rows.join(small(buckets, sum(r["count"] for r in known)), ["depth", "prefix"])
    name = F.concat_ws("-", F.col("depth").cast("string"), F.lower(F.hex("prefix")), F.col("page").cast("string"))
    plain = found.where((F.col("bucket_bytes") <= limit) | (F.col("n") == 1)).select("doc_id", "h", "bytes", "depth", "prefix", F.lit(0).cast("long").alias("page"), F.col("bucket_bytes").alias("shard_bytes"), *more)
    if any(r["depth"] == BITS for r in known):
        plain = plain.unionByName(_paged(found.where((F.col("bucket_bytes") > limit) & (F.col("n") > 1)), limit, *more))
    return plain.select("doc_id", "h", "bytes", name.alias("shard"), "shard_bytes", *more)


def _paged(rows: DataFrame, limit: int, *more: str) -> DataFrame:
    """Overflow pages; rows are numbered within slices, so that no task gets a whole bucket."""
    rows = cut(rows.withColumn("nth", F.monotonically_increasing_id()))
    half = F.lit(limit / 2)
    slices = F.greatest(F.lit(1), F.ceil(F.col("bucket_bytes") / (64 * limit)))
    rows = rows.withColumns({"slice": F.pmod(F.xxhash64("nth"), slices), "big": F.col("bytes") > half})
    order = Window.partitionBy("depth", "prefix", "slice", "big").orderBy("nth")
    before = F.sum("bytes").over(order) - F.col("bytes")
    own = F.when(F.col("big"), F.row_number().over(order)).otherwise(F.floor(before / half))
    rows = rows.withColumn("part", own)
    page = F.xxhash64("slice", "big", "part").bitwiseAND(F.lit(2**62 - 1))
    return rows.withColumn("page", page).withColumn("shard_bytes", F.sum("bytes").over(Window.partitionBy("depth", "prefix", "page"))).select("doc_id", "h", "bytes", "depth", "prefix", "page", "shard_bytes", *more)


def write(docs: DataFrame, limit: int, path: str) -> None:
    """The rows of ``docs`` as Parquet, a folder for each shard, overflow pages too."""
    found = _assigned(docs.select("doc_id", "text", F.struct(*docs.columns).alias("_row")), limit, "_row")
    found.select("_row.*", "shard").repartition("shard").write.partitionBy("shard").parquet(path)
