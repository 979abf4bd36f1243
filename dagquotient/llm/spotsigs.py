"""Document fingerprints by spot signatures.

Common words of a few languages are anchors; a signature is an anchor with the chain of the next two content words
behind it, looked for within ``REACH`` words. The set of a text's signatures, as sorted 32-bit hashes, is its
fingerprint; likeness is the Jaccard coefficient of two sets. A text without any signature is taken by all pairs of
its words, one without two words by its whole text, so that no two different texts are alike for want of signatures.

``near`` joins near-duplicates: equal sets form classes, classes are partitioned by set length, and only those of
compatible length that share one of the rarest signatures (as many as the threshold makes necessary) are compared.

A null text counts as empty. Repeated rows have equal fingerprints; equal ids are ordered by a hash of their text.
Extra columns are ignored, an empty table gives an empty table, and a single row is its own next document.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.llm.common import cut, let, width

#: Anchors: fixed values, the commonest function words of English, German, French and Spanish.
ANCHORS = "the of and to a in is that it was for on are as with they be at this have from or by not but what all were when we there can an der die das und zu den von ist mit des auf für ein eine dem nicht als auch es le la les et un une du que qui dans pour est par sur pas el los las en y se del una por con su para".split()
CHAIN, REACH = 2, 6


def signatures(text: Column) -> Column:
    """The sorted distinct hashes of a text's signatures, the first 32 bits of MD5 as a number."""
    text = F.coalesce(text, F.lit(""))

    def spots(w: Column) -> Column:
        def at(x: Column, i: Column) -> Column:
            chain = F.slice(F.filter(F.slice(w, i + 2, REACH), lambda y: ~y.isin(ANCHORS)), 1, CHAIN)
            return F.when(x.isin(ANCHORS), let(chain, lambda c: F.when(F.size(c) == CHAIN, F.concat_ws(" ", F.lit("3"), x, c))))

        found = F.filter(F.transform(w, at), lambda h: h.isNotNull())
        pairs = F.transform(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), lambda x, i: F.concat_ws(" ", F.lit("2"), x, F.get(w, i + 1)))
        return let(found, lambda f: F.when(F.size(f) > 0, f).when(F.size(w) > 1, pairs).otherwise(F.array(F.concat(F.lit("1 "), text))))

    found = let(F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != ""), spots)
    return F.sort_array(F.array_distinct(F.transform(found, lambda x: F.conv(F.substring(F.md5(x), 1, 8), 16, 10).cast("long"))))


def as_string(sigs: Column) -> Column:
    """The fingerprint: eight hexadecimal digits a signature, in order."""
    return F.array_join(F.transform(sigs, lambda h: F.lpad(F.lower(F.hex(h)), 8, "0")), ",")


def likeness(a: Column, b: Column) -> Column:
    """Jaccard coefficient of two arrays of distinct values."""
    common = F.size(F.array_intersect(a, b))
    return let(common, lambda n: F.when(F.size(a) + F.size(b) > 0, n / (F.size(a) + F.size(b) - n)).otherwise(F.lit(1.0))).cast("double")


def with_next(rows: DataFrame, columns: list[str], prepared=lambda df: df) -> DataFrame:
    """``prepared(rows)`` (d and th order them, both falling) and ``next``: a struct of ``columns`` of the next row.

    After the last row comes the first. Rows are dealt to ranges of ``d`` between quantiles; the head of each range is
    repeated at the end of the range above, so that every row finds its next one in its own range.
    """
    ranges = max(1, 2 * width(rows.sparkSession))
    ids = rows.select("d")
    cuts = ids.agg(F.percentile_approx("d", F.array(*[F.lit(k / ranges) for k in range(1, ranges)] or [F.lit(0.5)]), F.lit(10_000)).alias("q")).first()["q"] or []
    cuts = sorted(set(cuts)) if ranges > 1 else []
    # one boundary for each range: a list as long as the number of shuffle partitions allows
    place = F.size(F.filter(F.array(*[F.lit(c) for c in cuts]).cast("array<long>"), lambda c: c < F.col("d"))) if cuts else F.lit(0)
    heads = [(r["p"], r["top"]) for r in ids.select(place.alias("p"), "d").groupBy("p").agg(F.max("d").alias("top")).collect()]
    heads.sort()
    tops = [(heads[k - 1][1], heads[k][0]) for k in range(len(heads))]  # the lowest range is followed by the highest
    above = rows.sparkSession.createDataFrame(tops, "d long, p int")
    ghosts = rows.join(F.broadcast(above), "d").withColumn("ghost", F.lit(1))
    both = prepared(rows.withColumns({"p": place, "ghost": F.lit(0)}).unionByName(ghosts))
    order = Window.partitionBy("p").orderBy("ghost", F.desc("d"), F.desc("th"))
    return both.withColumn("next", F.lead(F.struct(*columns)).over(order)).where("ghost = 0").drop("p", "ghost")


def edited(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", F.coalesce("doc_id", F.lit(-(2**63))).alias("d"), F.xxhash64(text).alias("th"), text.alias("text"))
    rows = with_next(rows, ["text", "sigs"], lambda df: df.withColumn("sigs", signatures(F.col("text"))))
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    new = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next.text"), F.lit(1), half))
    rows = rows.select("doc_id", n.cast("long").alias("n_chars"), "sigs", F.col("next.sigs").alias("next_sigs"), new.alias("new"))
    rows = rows.withColumn("new_sigs", signatures(F.col("new")))
    return rows.select("doc_id", "n_chars", F.sha2("new", 256).alias("edited_sha256"), as_string(F.col("sigs")).alias("fingerprint"), as_string(F.col("new_sigs")).alias("edited_fingerprint"), likeness(F.col("sigs"), F.col("new_sigs")).alias("near_edited"), likeness(F.col("sigs"), F.col("next_sigs")).alias("near_next"))


def near(docs: DataFrame, threshold: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """(doc_id, class_id) of every row, and (a, b, likeness) of all pairs of classes that are alike, a < b.

    A class is a set of signatures, its id the smallest doc_id that has it.
    """
    rows = cut(docs.select("doc_id", signatures(F.col("text")).alias("sigs")))
    key = [F.xxhash64("sigs").alias("k1"), F.xxhash64("sigs", F.lit(1)).alias("k2")]
    ids = rows.select("doc_id", *key).groupBy("k1", "k2").agg(F.min("doc_id").alias("class_id"))
    member = rows.select("doc_id", *key).join(ids, ["k1", "k2"]).select("doc_id", "class_id")
    classes = cut(rows.select("sigs", "doc_id", *key).join(ids, ["k1", "k2"]).where(F.col("doc_id").eqNullSafe(F.col("class_id"))).dropDuplicates(["k1", "k2"]).select("class_id", "k1", "sigs", F.size("sigs").alias("n")))
    each = classes.select("class_id", "k1", "n", F.explode("sigs").alias("s"))
    rank = F.row_number().over(Window.partitionBy("k1", "class_id").orderBy("df", "s"))
    need = F.col("n") - F.ceil(F.lit(threshold) * F.col("n") - 1e-9) + 1
    prefix = each.join(each.groupBy("s").agg(F.count("*").alias("df")), "s").withColumn("r", rank).where(F.col("r") <= need)
    # partitions of set length: a class joins those of its own and of the next span, which reach to n / threshold
    span = F.floor(F.log(F.col("n").cast("double")) / F.lit(-math.log(threshold)))
    left = prefix.select("s", F.col("class_id").alias("a"), F.col("n").alias("na"), F.col("r").alias("ra"), F.explode(F.array(span, span + 1)).alias("span"))
    right = prefix.select("s", F.col("class_id").alias("b"), F.col("n").alias("nb"), F.col("r").alias("rb"), span.alias("span"))
    apart = (F.col("na") < F.col("nb")) | ((F.col("na") == F.col("nb")) & (F.col("a") < F.col("b")))
    reach = F.least(F.col("na") - F.col("ra"), F.col("nb") - F.col("rb")) + F.least("ra", "rb")
    possible = (F.col("na") >= threshold * F.col("nb") - 1e-9) & (reach * (1 + threshold) >= threshold * (F.col("na") + F.col("nb")) - 1e-9)
    pairs = left.join(right, ["s", "span"]).where(apart & possible).select("a", "b").distinct()
    pairs = pairs.join(classes.select(F.col("class_id").alias("a"), F.col("sigs").alias("sa")), "a").join(classes.select(F.col("class_id").alias("b"), F.col("sigs").alias("sb")), "b")
    return member, pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), likeness(F.col("sa"), F.col("sb")).alias("likeness")).where(F.col("likeness") >= threshold)
