"""Benchmark decontamination: a prefix-filtered join of item windows with documents.

Texts become words and words become shingles of up to three words. All shingles of the items are counted over all
documents, which orders them by rarity. A window of an item can only occur where its rarest shingle does, so that one
alone is joined (exact containment needs a prefix of one); each match fixes a diagonal, the offset of the item against
the document. The item's positions along the diagonal, clipped to the document, are then verified shingle by shingle,
and runs as long as a window are occurrences.

Null texts and texts without words have no windows and no hits. Repeated rows (one id, one text) get equal results;
items that share an id count as one item. Null ids are kept. Extra columns are ignored, an empty benchmark hits
nothing. Shingles are compared by 64-bit hashes: a window of ten words with one wrong word would have to meet three
equal hashes at once.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.llm.common import cut, let, packed, small

#: What parts words (fixed by the contract): ASCII other than letters and digits.
GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
SHINGLE = 3
_NO_ID = -(2**63)


def words(text: Column) -> Column:
    lowered = F.translate(F.coalesce(text, F.lit("")), string.ascii_uppercase, string.ascii_lowercase)
    return F.filter(F.split(lowered, GAPS), lambda w: w != "")


def _shingles(w: Column, m: int) -> Column:
    """An array of hashes of ``m`` words each, for words ``w`` (a lambda variable)."""
    return F.transform(F.slice(w, 1, F.greatest(F.size(w) - (m - 1), F.lit(0))), lambda x, i: F.xxhash64(F.lit(m), x, *[F.get(w, i + k) for k in range(1, m)]))


def _placed(w: Column, sizes: list[int]) -> Column:
    """pos and h of every shingle of the given sizes."""
    each = [F.transform(_shingles(w, m), lambda h, i: F.struct(i.cast("int").alias("pos"), h.alias("h"))) for m in sizes]
    return each[0] if len(each) == 1 else F.concat(*each)


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "text").select("doc_id", F.coalesce("doc_id", F.lit(_NO_ID)).alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"), "text")


def hits(docs: DataFrame, benchmark: DataFrame, window: int) -> DataFrame:
    """d, th, item_id, first, last: maximal runs of document words that occurrences of an item's windows cover."""
    items = benchmark.select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0).dropDuplicates(["item_id", "w"])
    items = items.select(F.xxhash64("item_id", "w").alias("ik"), "item_id", "w", F.size("w").alias("n"))
    items = items.withColumn("m", F.least(F.lit(SHINGLE), F.lit(window), "n")).withColumn("need", F.least(F.lit(window), "n") - F.col("m") + 1)
    items = cut(items)
    sizes = sorted(r["m"] for r in items.select("m").distinct().collect())  # three at most
    if not sizes:
        return docs.sparkSession.createDataFrame([], "d long, th long, item_id long, first int, last int")
    placed = F.coalesce(*[F.when(F.col("m") == m, _placed(F.col("w"), [m])) for m in sizes])
    at = cut(items.select("ik", "item_id", "n", "m", "need", F.explode(placed).alias("s")).select("ik", "item_id", "n", "m", "need", F.col("s.pos").alias("ip"), F.col("s.h").alias("h")))
    vocabulary = at.select("h").distinct()
    n = at.count()
    found = _keyed(docs).select("d", "th", F.explode(let(words(F.col("text")), lambda w: _placed(w, sizes))).alias("s")).select("d", "th", F.col("s.pos").alias("pos"), F.col("s.h").alias("h"))
    found = cut(found.join(small(vocabulary, n), "h", "left_semi"))

    rarity = found.groupBy("h").agg(F.count("*").alias("df"))
    ranked = at.join(rarity, "h")  # a window with a shingle that no document has can't occur: its count falls short
    starts = F.sequence(F.greatest(F.lit(0), F.col("ip") - F.col("need") + 1), F.least(F.col("ip"), F.col("n") - F.col("m") - F.col("need") + 1))
    per_window = ranked.select("*", F.explode(starts).alias("start")).groupBy("ik", "start").agg(F.min(F.struct("df", "h", "ip")).alias("rare"), F.count("*").alias("there"), F.first("need").alias("need"))
    prefix = per_window.where(F.col("there") == F.col("need")).select("ik", F.col("rare.ip").alias("ip"), F.col("rare.h").alias("h")).distinct()

    diagonals = found.join(small(prefix, n), "h").select("d", "th", "ik", (F.col("pos") - F.col("ip")).alias("diag")).distinct()
    expected = diagonals.join(small(at, n), "ik").where(F.col("diag") + F.col("ip") >= 0)
    expected = expected.select("d", "th", "ik", "item_id", "diag", "m", "need", (F.col("diag") + F.col("ip")).alias("pos"), "h")
    same = expected.join(found, ["d", "th", "pos", "h"], "left_semi")
    order = Window.partitionBy("d", "th", "ik", "diag").orderBy("pos")
    runs = same.withColumn("run", F.col("pos") - F.row_number().over(order)).groupBy("d", "th", "ik", "diag", "run").agg(F.min("pos").alias("first"), F.count("*").alias("n"), F.first("m").alias("m"), F.first("need").alias("need"), F.first("item_id").alias("item_id"))
    return runs.where(F.col("n") >= F.col("need")).select("d", "th", "item_id", "first", (F.col("first") + F.col("n") + F.col("m") - 2).cast("int").alias("last"))


def report(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_words, n_hit, items (sorted as strings), contaminated."""
    runs = hits(docs, benchmark, window)
    order = Window.partitionBy("d", "th").orderBy("first", "last")
    before = F.max("last").over(order.rowsBetween(Window.unboundedPreceding, -1))
    fresh = runs.withColumn("fresh", F.greatest(F.lit(0), F.col("last") - F.greatest(F.col("first"), F.coalesce(before + 1, F.col("first"))) + 1))
    per_doc = fresh.groupBy("d", "th").agg(F.sum("fresh").alias("n_hit"), F.collect_set(F.col("item_id").cast("string")).alias("items"))
    docs = _keyed(docs).select("doc_id", "d", "th", F.size(words(F.col("text"))).cast("long").alias("n_words"))
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    items = F.coalesce(F.array_sort("items"), F.array().cast("array<string>"))
    return docs.join(per_doc, ["d", "th"], "left").select("doc_id", "n_words", n_hit.alias("n_hit"), items.alias("items"), (n_hit > 0).alias("contaminated"))


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """The rows of ``docs`` that no window of the benchmark occurs in."""
    bad = hits(docs, benchmark, window).select("d", "th").distinct()
    keyed = packed(docs, F.coalesce("doc_id", F.lit(_NO_ID)).alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"))
    return keyed.join(bad, ["d", "th"], "left_anti").select("row.*")
