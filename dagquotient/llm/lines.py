"""Line dedup by distinct-site spread.

For every line, the number of distinct sites (``source``) that print it is estimated by HyperLogLog sketches that
merge by aggregation. Lines whose estimate is near the threshold get an exact distinct count; only then are lines of
``min_sites`` sites or more taken for cross-site boilerplate. Of such a line the first copy stays (smallest doc_id,
then the earliest line), all others go.

Lines are parts between newlines, compared after their outer spaces are taken off, by 128 bits of hash; blank lines
never go. A null text counts as empty, a null source as one more site, a null doc_id as larger than all. Rows with one
doc_id and one text (repeated rows) keep or lose the same lines. All rows stay, also those with no line left; extra
columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import cut, let, packed, small

#: Sketch precision (2**LG_K registers) and the band around the threshold in which sites are counted exactly.
LG_K, BAND = 10, 0.25


def _line(raw: Column) -> Column:
    return F.trim(raw)


def _keys(line: Column) -> list[Column]:
    return [F.xxhash64(line).alias("h1"), F.xxhash64(line, F.lit("line")).alias("h2")]


def _lines(docs: DataFrame) -> DataFrame:
    """d, site, h1, h2 of every line that isn't blank."""
    order = F.coalesce(F.col("doc_id"), F.lit(2**63 - 1))
    lines = docs.select(order.alias("d"), F.xxhash64(F.coalesce("source", F.lit("\0"))).alias("site"), F.explode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("raw"))
    return lines.select("d", "site", _line(F.col("raw")).alias("line")).where(F.col("line") != "").select("d", "site", *_keys(F.col("line")))


def spread(docs: DataFrame, min_sites: int) -> DataFrame:
    """h1, h2, first_doc, sites_about, sites: the lines on ``min_sites`` sites or more.

    Every task makes a sketch of its part of a line's sites, and sketches of one line are merged. Lines are read again
    only for those whose estimate is near the threshold, to count their distinct sites.
    """
    lines = _lines(docs)
    sketched = lines.groupBy("h1", "h2").agg(F.hll_sketch_agg("site", F.lit(LG_K)).alias("sketch"), F.min("d").alias("first_doc"))
    about = sketched.select("h1", "h2", "first_doc", F.hll_sketch_estimate("sketch").alias("sites_about"))
    about = cut(about.where(F.col("sites_about") >= min_sites * (1 - BAND)))
    close = F.col("sites_about") <= min_sites * (1 + BAND)
    far = about.where(~close).withColumn("sites", F.lit(None).cast("long"))
    near = about.where(close)
    exact = lines.join(small(near.select("h1", "h2"), near.count()), ["h1", "h2"], "left_semi").select("h1", "h2", "site").distinct().groupBy("h1", "h2").agg(F.count("*").alias("sites"))
    return far.unionByName(near.join(exact.where(F.col("sites") >= min_sites), ["h1", "h2"]))


def dedup(docs: DataFrame, min_sites: int = 8) -> DataFrame:
    """The columns of ``docs`` (text without its cross-site lines) and ``n_lines``, ``n_removed``, which replace columns of these names."""
    spare = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    found = cut(spread(docs, min_sites))
    n = found.count()
    order = F.coalesce(F.col("doc_id"), F.lit(2**63 - 1))
    rows = packed(docs.select(*spare), order.alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("t"))
    lines = rows.select("d", "t", F.posexplode(F.split(F.coalesce("row.text", F.lit("")), "\n")).alias("pos", "raw"))
    lines = lines.select("d", "t", "pos", *_keys(_line(F.col("raw"))))
    hits = lines.join(small(found.select("h1", "h2", "first_doc"), n), ["h1", "h2"])
    # within the first document the earliest copy stays
    per_line = hits.groupBy("d", "t", "h1", "h2").agg(F.min("pos").alias("earliest"), F.collect_set("pos").alias("all"), F.first("first_doc").alias("first_doc"))
    gone = per_line.select("d", "t", F.when(F.col("d") == F.col("first_doc"), F.array_except("all", F.array("earliest"))).otherwise(F.col("all")).alias("gone"))
    gone = cut(gone.groupBy("d", "t").agg(F.flatten(F.collect_list("gone")).alias("gone")))
    marked = rows.join(gone, ["d", "t"], "left")
    split = F.split(F.coalesce("row.text", F.lit("")), "\n")
    kept = let(split, lambda x: F.transform(F.array_except(F.sequence(F.lit(0), F.size(x) - 1), F.col("gone")), lambda i: F.get(x, i)))
    size = F.when(F.size("gone") > 0, F.size("gone")).otherwise(0)
    text = F.when(size > 0, F.array_join(kept, "\n")).otherwise(F.col("row.text"))
    return marked.select(*[text.alias("text") if c == "text" else F.col(f"row.`{c}`").alias(c) for c in spare], F.size(split).cast("long").alias("n_lines"), size.cast("long").alias("n_removed"))
