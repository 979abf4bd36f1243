"""N-gram Jaccard join as a blocked sparse matrix product.

Documents are rows, word n-grams columns of an incidence matrix; the product of the matrix with its transpose holds
the overlaps. It is not formed as a whole:

* equal sets are one class (they are linked anyway);
* n-grams are ordered by rarity (a heavy-hitter sketch over all documents, as only common ones matter). Two sets of
  which ``percent`` must be common share at least k n-grams among the first ones of each, for any k, if these are taken
  k - 1 further; k grows with the set. An n-gram that several classes have in front gives a list of classes;
* classes that share one of two keys, each of the least n-grams by two orders, meet in blocks of bounded rows and
  entries, where their whole sets are multiplied. That finds most links; from then on only classes that are not
  connected yet are looked at, which changes no component;
* over short lists the product of the fronts is accumulated pair by pair, over longer ones in blocks, column by column.
  What is common in front and the sizes bound the overlap of a pair; pairs below what their sizes ask for are
  discarded. Blocks pass on what connects the others as stars: as many rows as classes, not as pairs;
* classes that such pairs connect make groups. Those of a group meet in blocks, where whole sets are multiplied. In
  lists and groups of several blocks, all but the largest component meet every block.

The outcome is exact: components over all links. Sets are compared by 64-bit hashes of n-grams.

Nulls and texts without words have empty sets and are linked with nothing. Repeated rows share a class, rows with a
null id belong to components but name none. Extra columns are ignored, an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import among, cut, drop, freed, packed, sieve, small, told, trimmed, without
from dagquotient.llm.components import components

#: Rows of a block, entries that are sorted at once, and n-grams that the sketch of common ones keeps: they come last.
BLOCK_ROWS, BLOCK_ENTRIES, COMMON = 256, 2_000_000, 100_000
#: Rows of a table up to which the driver builds it for a broadcast: it holds several at once.
MOST = 200_000
#: Classes of a list whose pairs are accumulated one by one.
SHORT = 16
#: Bytes that are hashed together.
CHUNK = 2_000_000
_NO_ID = -(2**63)
#: What parts words (fixed by the contract), random numbers of bytes, alike for a letter's two cases, and their base.
_GAP = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
_MIX = np.random.default_rng(20240301).integers(0, 2**64, 256, dtype=np.uint64)
_MIX[0x41:0x5B] = _MIX[0x61:0x7B]
_BASE = 0x9E3779B97F4A7C13
_grown = [np.ones(1, np.uint64), np.ones(1, np.uint64)]
#: Odd factors: that of mixing, and those that order hashes anew.
_ODD = np.uint64(0x9E3779B97F4A7C15)
_ORDERS = [np.int64(x) for x in (1, 0x5851F42D4C957F2D, 0x2545F4914F6CDD1D, 0x369DEA0F31A53F85)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``n`` powers of the base of byte hashes, and of its inverse, modulo 2**64."""
    if len(_grown[0]) < n:
        _grown[:] = [np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(n, x, np.uint64)])) for x in (_BASE, pow(_BASE, -1, 2**64))]
    return _grown[0], _grown[1]


def word_hashes(raw: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of texts that follow each other in ``raw``: a hash of each word, and how many words each text has.

    Words are parted by ``[\\x20\\x09-\\x0D]+`` and compared with A to Z lower-cased, as the contract says: two tables
    over bytes. A word's hash is a polynomial over its bytes, taken from running sums over a few megabytes.
    """
    inside = ~_GAP[raw]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    bounds = ends[(ends > 0) & (ends < len(raw))]
    first[bounds] = inside[bounds]
    last = inside.copy()
    last[:-1] &= ~inside[1:] | first[1:]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    counts = np.diff(np.searchsorted(start, ends), prepend=0)
    out = np.empty(len(start), np.uint64)
    at = 0
    while at < len(start):
        to = max(at + 1, int(np.searchsorted(end, start[at] + CHUNK, side="right")))
        low, high = int(start[at]), int(end[to - 1])
        power, inverse = _powers(high - low + 1)
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_MIX[raw[low:high]] * power[: high - low])])
        s, e = start[at:to] - low, end[at:to] - low
        out[at:to] = (sums[e] - sums[s]) * inverse[s] + (e - s).astype(np.uint64)
        at = to
    out ^= out >> np.uint64(32)
    return out * np.uint64(0xD6E8FEB86659FD93), counts


def _distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sorted distinct values and their counts."""
    values = np.sort(values)
    at = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.zeros(0, np.int64)
    return values[at], np.diff(np.append(at, len(values)))


def _mixed(h: np.ndarray, n: int) -> np.ndarray:
    """The hashes of all runs of ``n`` of the given word hashes."""
    out = h[: len(h) - n + 1] * _ODD
    for k in range(1, n):
        out ^= out >> np.uint64(31)
        out = (out + h[k : len(h) - n + 1 + k]) * _ODD
    return out ^ (out >> np.uint64(29))


def sets(texts: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The sorted distinct hashes of each text's n-grams, one after the other, and where each text's begin and end.

    A text of fewer than ``n`` words has one of all its words, one without words none; null counts as empty.
    """
    texts = pc.fill_null(texts.cast(pa.large_binary()), b"")
    _, offsets, data = texts.buffers()
    ends = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    raw = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if len(texts) and ends[-1] > ends[0] else np.zeros(0, np.uint8)
    h, sizes = word_hashes(raw, ends[1:] - ends[0]) if len(raw) else (np.zeros(0, np.uint64), np.zeros(len(texts), np.int64))
    grams = _mixed(h, n).view(np.int64) if len(h) >= n else np.zeros(0, np.int64)
    out, start = [], 0
    for size in sizes.tolist():
        if size >= n:
            out.append(_distinct(grams[start : start + size - n + 1])[0])
        elif size:
            out.append((_mixed(h[start : start + size], size) + np.uint64(size)).view(np.int64))
        else:
            out.append(grams[:0])
        start += size
    return np.concatenate([*out, grams[:0]]), np.concatenate([[0], np.cumsum([len(x) for x in out], dtype=np.int64)])


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches whose texts have about ``CHUNK`` bytes; a longer text is a batch of its own."""
    for batch in batches:
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        start = 0
        while start < batch.num_rows:
            stop = max(start + 1, int(np.searchsorted(size, (size[start - 1] if start else 0) + CHUNK, side="right")))
            yield batch.slice(start, stop - start)
            start = stop


def _small(df: DataFrame, rows: int) -> DataFrame:
    return small(df, rows, MOST)


def _least(size):
    """k: n-grams that two sets must share in front; ``size`` is that of the smaller one."""
    return 1 + size // 100


def _front(size: int, percent: int) -> int:
    """How many of a set's n-grams are in front: k more than may be missing from the other set."""
    return size - (size * percent + 99) // 100 + _least(size)


def _common(docs: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes (sorted) and counts of the most common n-grams: at most ``COMMON`` of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[np.ndarray] = []

        def out() -> pa.RecordBatch:
            values, counts = _distinct(np.concatenate(kept))
            often = counts >= 2
            return pa.RecordBatch.from_arrays([pa.array(values[often]), pa.array(counts[often])], ["h", "df"])

        for batch in _batches(batches):
            kept.append(sets(batch.column("text"), n)[0])
            if sum(map(len, kept)) > BLOCK_ENTRIES:
                yield out()
                kept.clear()
        if kept:
            yield out()

    with freed(docs.sparkSession):
        found = docs.select("text").mapInArrow(trimmed(run), "h long, df long").groupBy("h").agg(F.sum("df").alias("df")).orderBy(F.desc("df"), "h").limit(COMMON).toPandas()
    found = found.sort_values("h")
    return found["h"].to_numpy(np.int64), found["df"].to_numpy(np.int64)


def _fronts(docs: DataFrame, n: int, percent: int) -> DataFrame:
    """d, th, cid, n, low, high, front: a hash of each set, its size, two keys that like sets tend to share, its front.

    Each key is made of the least hashes by two orders. Sets are not kept: they are two to three times as large as the
    texts.
    """
    keys, counts = (docs.sparkSession.sparkContext.broadcast(x) for x in _common(docs, n))  # ``COMMON`` numbers each

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common, df_of = keys.value, counts.value
        for batch in _batches(batches):
            values, at = sets(batch.column("text"), n)
            sizes = np.diff(at)
            some = np.flatnonzero(sizes)
            low, high, cid = (np.zeros(len(sizes), np.int64) for _ in range(3))
            fronts = [values[:0]] * len(sizes)
            if len(some):
                begin = at[some]
                least = [np.minimum.reduceat(values * odd, begin) for odd in _ORDERS]
                low[some], high[some] = (a * _ORDERS[2] ^ b for a, b in (least[:2], least[2:]))
                place = np.searchsorted(common, values)
                place[place == len(common)] = 0
                df = np.where(common[place] == values, df_of[place], 0) if len(common) else np.zeros(len(values), np.int64)
                for k in some.tolist():
                    s = values[at[k] : at[k + 1]]
                    cid[k] = xxhash.xxh64_intdigest(s.tobytes()) - 2**63
                    fronts[k] = s[np.argsort(df[at[k] : at[k + 1]], kind="stable")[: _front(len(s), percent)]]
            front = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in fronts])]), pa.int32()), pa.array(np.concatenate([*fronts, values[:0]])))
            yield pa.RecordBatch.from_arrays([batch.column("d"), batch.column("th"), *(pa.array(x, pa.int64()) for x in (cid, sizes, low, high)), front], ["d", "th", "cid", "n", "low", "high", "front"])

    import xxhash

    return docs.select(*_row_keys(), "text").mapInArrow(trimmed(run), "d long, th long, cid long, n long, low long, high long, front array<long>")


def _sets_of(texts: DataFrame, n: int) -> DataFrame:
    """cid, s: the sets of the texts of rows of cid and text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _batches(batches):
            values, at = sets(batch.column("text"), n)
            yield pa.RecordBatch.from_arrays([batch.column("cid"), pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(values))], ["cid", "s"])

    return texts.select("cid", "text").mapInArrow(trimmed(run), "cid long, s array<long>")


def overlaps(which: np.ndarray, values: np.ndarray, rows: int) -> np.ndarray:
    """The product of an incidence matrix with its transpose: ``which`` row has which of the ``values``."""
    _, column, count = np.unique(values, return_inverse=True, return_counts=True)
    out = np.zeros((rows, rows), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = which[order], column[order]
    few = (count[column] > 1) & (count[column] <= 16)
    row_few, column_few = row[few], column[few]
    for step in range(1, 16):  # pairs of entries of one column, by their distance in it
        same = column_few[step:] == column_few[:-step]
        if not same.any():
            break
        np.add.at(out, (row_few[:-step][same], row_few[step:][same]), 1)
    out += out.T
    many = np.flatnonzero(count > 16)
    place = np.full(len(count), -1)
    place[many] = np.arange(len(many))
    wide = place[column] >= 0
    row, column = row[wide], place[column[wide]]
    for start in range(0, len(many), 4096):
        part = (column >= start) & (column < start + 4096)
        dense = np.zeros((rows, min(4096, len(many) - start)), np.float32)
        dense[row[part], column[part] - start] = 1
        out += dense @ dense.T
    return out


def stars(linked: np.ndarray) -> np.ndarray:
    """For each row the least row that it is connected with, in a boolean matrix."""
    root = np.arange(len(linked))
    seen = np.zeros(len(linked), bool)
    for start in np.flatnonzero(linked.any(axis=0)).tolist():
        if not seen[start]:
            front = np.array([start])
            seen[start] = True
            while len(front):
                root[front] = start
                front = np.flatnonzero(linked[front].any(axis=0) & ~seen)
                seen[front] = True
    return root


def _needed(size, other, percent: int):
    """The overlap that two sets of these sizes must have."""
    return -(-percent * (size + other) // (100 + percent))


def _behind(size, percent: int):
    """How many n-grams of a set aren't in its front."""
    return (size * percent + 99) // 100 - size // 100 - 1


def _block(table: pa.Table, column: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """cid, n and root of the classes of a block, and the overlaps of what is in ``column``."""
    cids, first = np.unique(table.column("cid").to_numpy(), return_index=True)
    held = table.take(pa.array(first)).combine_chunks()
    values = held.column(column).combine_chunks()
    product = overlaps(np.repeat(np.arange(len(cids)), pc.list_value_length(values).to_numpy(zero_copy_only=False)), values.flatten().to_numpy(), len(cids))
    return cids, held.column("n").to_numpy(), held.column("root").to_numpy(), product.astype(np.int64)


def _starred(cids: np.ndarray, which: np.ndarray) -> pa.Table:
    root = stars(which)
    far = root != np.arange(len(cids))
    return pa.table({"a": cids[far], "b": cids[root[far]]}, schema=pa.schema([("a", pa.int64()), ("b", pa.int64())]))


def _alike(percent: int):
    """a, b: what connects the classes of a block that may be linked and aren't connected, by what is in front.

    Of a front only 32 bits of each n-gram are looked at, which can only make overlaps larger.
    """

    def run(table: pa.Table) -> pa.Table:
        cids, n, root, product = _block(table, "front")
        x, y, behind = n[:, None], n[None, :], _behind(n, percent)
        may = (root[:, None] != root[None, :]) & (100 * np.minimum(x, y) >= percent * np.maximum(x, y))
        return _starred(cids, may & (product + np.maximum(behind[:, None], behind[None, :]) >= _needed(x, y, percent)))

    return run


def _links(percent: int):
    """a, b: what connects the classes of a block that are linked, by whole sets."""

    def run(table: pa.Table) -> pa.Table:
        cids, n, _, product = _block(table, "s")
        return _starred(cids, 100 * product >= percent * (n[:, None] + n[None, :] - product))

    return run


def _sql_needed(x: Column, y: Column, percent: int) -> Column:
    return F.ceil(percent * (x + y) / (100 + percent))


def _sql_behind(size: Column, percent: int) -> Column:
    return F.ceil(size * percent / 100) - F.floor(size / 100) - 1


def _fit(x: Column, y: Column, percent: int) -> Column:
    return 100 * F.least(x, y) >= percent * F.greatest(x, y)


def _pairs(short: DataFrame, percent: int) -> DataFrame:
    """a, b: pairs of classes that are not connected and may be linked, from short lists of h, cid, n, root."""
    held = short.groupBy("h").agg(F.array_sort(F.collect_list(F.struct("cid", "n", "root"))).alias("x"))

    def later(x: Column, i: Column) -> Column:
        like = F.filter(F.slice("x", i + 2, SHORT), lambda y: (x["root"] != y["root"]) & _fit(x["n"], y["n"], percent))
        return F.transform(like, lambda y: F.struct(x["cid"].alias("a"), y["cid"].alias("b"), x["n"].alias("na"), y["n"].alias("nb")))

    pairs = held.select(F.explode(F.flatten(F.transform("x", later))).alias("p")).select("p.*").groupBy("a", "b").agg(F.count("*").alias("common"), F.first("na").alias("na"), F.first("nb").alias("nb"))
    most = F.greatest(_sql_behind(F.col("na"), percent), _sql_behind(F.col("nb"), percent)) + F.col("common")
    return pairs.where(most >= _sql_needed(F.col("na"), F.col("nb"), percent)).select("a", "b")


def _blocks(members: DataFrame, entries: Column) -> DataFrame:
    """g, i, j, cid, n, root from g, cid, n, root: blocks of bounded rows and entries in which all pairs of a group meet
    that are not connected yet.

    All but the classes of a group's largest component meet every block of the group, themselves in parts. A group in
    which all are apart from each other has as many rows as blocks a class; one that is connected has none.
    """
    per_root = members.groupBy("g", "root").agg(F.count("*").alias("c"), F.sum(entries).alias("e"))
    main = per_root.groupBy("g").agg(F.max(F.struct("c", "e", "root")).alias("x"), F.sum("c").alias("m"), F.sum("e").alias("all"))
    parts = lambda rows, size: F.greatest(F.ceil(rows / BLOCK_ROWS), F.ceil(size / BLOCK_ENTRIES)).cast("long")
    main = cut(main.where("m > x.c").select("g", F.col("x.root").alias("main"), parts(F.col("m"), F.col("all")).alias("blocks"), parts(F.col("m") - F.col("x.c"), F.col("all") - F.col("x.e")).alias("parts")))
    both = members.join(_small(main, told(main)), "g")
    own = both.select("g", F.pmod(F.xxhash64("cid", "g"), "blocks").alias("i"), F.explode(F.expr("sequence(0L, parts - 1)")).alias("j"), "cid", "n", "root")
    visits = both.where("root <> main").select("g", F.explode(F.expr("sequence(0L, blocks - 1)")).alias("i"), F.pmod(F.xxhash64("g", "cid"), "parts").alias("j"), "cid", "n", "root")
    return own.union(visits).distinct()


def _met(blocks: DataFrame, classes: DataFrame, docs: DataFrame, n: int, percent: int) -> DataFrame:
    """a, b: what connects linked classes of the blocks, by the whole sets of one text of each class."""
    blocks = cut(blocks)
    asked = cut(blocks.select("cid").distinct())
    n_asked = told(asked)
    who = classes.join(_small(asked, n_asked), "cid", "left_semi").select("cid", "d", "th")
    sets_of = cut(_sets_of(among(docs.select(*_row_keys(), "text"), who, n_asked, "d", "th", most=MOST), n))
    if told(sets_of) > n_asked:  # rows alike in id and text
        sets_of = sets_of.dropDuplicates(["cid"])
    out = cut(sets_of.join(_small(blocks, told(blocks)), "cid").groupBy("g", "i", "j").applyInArrow(_links(percent), "a long, b long"))
    drop(blocks, asked, sets_of)
    return out


def _row_keys() -> list[Column]:
    return [F.coalesce("doc_id", F.lit(_NO_ID)).alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th")]


def _by_keys(classes: DataFrame) -> DataFrame:
    """g, i, j, cid, n, root: blocks of the classes that share a key, with the first of all of them in each."""
    out = None
    for key in ("low", "high"):
        groups = classes.groupBy(F.col(key).alias("g")).agg(F.min(F.struct("cid", "n")).alias("first"), F.count("*").alias("m"), F.sum("n").alias("e")).where("m > 1")
        groups = cut(groups.select("g", F.col("first.cid").alias("cid"), F.col("first.n").alias("n"), F.greatest(F.ceil(F.col("m") / BLOCK_ROWS), F.ceil(F.col("e") / BLOCK_ENTRIES)).cast("long").alias("blocks")))
        each = classes.join(_small(groups.select(F.col("g").alias(key), "blocks"), told(groups)), key).select(F.col(key).alias("g"), F.pmod(F.xxhash64("cid"), "blocks").alias("i"), "cid", "n")
        first = groups.where("blocks > 1").select("g", F.explode(F.expr("sequence(0L, blocks - 1)")).alias("i"), "cid", "n")
        rows = each.union(first).distinct().withColumns({"j": F.lit(0 if key == "low" else 1).cast("long"), "root": F.col("cid")})
        out = rows if out is None else out.unionByName(rows)
    return out.select("g", "i", "j", "cid", "n", "root")


def _rooted(df: DataFrame, roots: DataFrame, n_roots: int, of: str, name: str) -> DataFrame:
    """``df`` with the root of the class in ``of``, the class itself where it has no links."""
    roots = roots.select(F.col("node").alias(of), F.col("root").alias("_root"))
    return df.join(_small(roots, n_roots), of, "left").withColumn(name, F.coalesce("_root", of)).drop("_root")


def _candidates(rows: DataFrame, classes: DataFrame, roots: DataFrame, n_roots: int, percent: int) -> DataFrame:
    """a, b: what connects classes that ``roots`` does not connect and that may be linked, as far as fronts tell."""
    # of the classes of several rows the row that stands for each; only those are told to all tasks
    several = cut(classes.where("m > 1").select("cid", F.col("d").alias("_d"), F.col("th").alias("_th")))
    one = rows.where("n > 0").join(_small(several, told(several)), "cid", "left").where("_d IS NULL OR _d = d AND _th = th").select("cid", "n", "front")
    rooted = _rooted(one, roots, n_roots, "cid", "root")
    told_of = rooted.select("cid", "n", "root", F.explode("front").alias("h"))
    # only n-grams of classes that are not connected make lists: most that copies share are told apart here
    shared = cut(told_of.groupBy("h").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 <> r1").select("h"))
    # and a few others, of which nothing follows: a bitmap in place of the n-grams themselves goes to the driver
    postings = sieve(shared, told(shared), "h")(told_of).where("may").drop("may")
    if one.select("cid").count() > told(classes):  # rows alike in id and text
        postings = postings.dropDuplicates(["h", "cid"])
    postings = cut(postings)
    drop(shared, several)
    mixed = F.xxhash64("cid")
    lists = postings.groupBy("h").agg(F.count("*").alias("m"), F.bit_xor(mixed).alias("x"), F.sum(F.shiftright(mixed, 24)).alias("y"), (F.min("root") != F.max("root")).alias("apart"))
    lists = cut(lists.where(F.col("m") > SHORT))
    pairs = cut(_pairs(postings.join(_small(lists.select("h"), told(lists)), "h", "left_anti"), percent))
    # longer lists, one of each membership
    long_ = cut(lists.where("apart").groupBy("m", "x", "y").agg(F.min("h").alias("h")).select("h"))
    drop(lists)
    n_long = told(long_)
    if not n_long:
        drop(postings, long_)
        return pairs
    members = cut(postings.join(_small(long_, n_long), "h").select(F.col("h").alias("g"), "cid", "n", "root"))
    drop(postings, long_)
    asked = cut(members.select("cid").distinct())
    who = cut(classes.select("cid", "d", "th").join(_small(asked, told(asked)), "cid", "left_semi"))
    fronts = rows.join(_small(who, told(who)), ["cid", "d", "th"]).select("cid", F.transform("front", lambda x: x.bitwiseAND(F.lit(2**31 - 1)).cast("int")).alias("front"))
    fronts = cut(fronts.dropDuplicates(["cid"]))
    drop(asked, who)
    met = cut(_blocks(members, _sql_front(F.col("n"), percent)))
    found = cut(fronts.join(_small(met, told(met)), "cid").groupBy("g", "i", "j").applyInArrow(_alike(percent), "a long, b long"))
    out = cut(pairs.union(found).distinct())
    drop(pairs, found, members, fronts, met)
    return out


def _sql_front(size: Column, percent: int) -> Column:
    return size - _sql_behind(size, percent)


def _class_roots(rows: DataFrame, docs: DataFrame, n: int, percent: int) -> DataFrame:
    """node, root of every class that has links: what is connected has one root; ``rows``: what ``_fronts`` gives."""
    classes = rows.where("n > 0").groupBy("cid").agg(F.min(F.struct("d", "th")).alias("x"), F.count("*").alias("m"), *[F.first(c).alias(c) for c in ("n", "low", "high")])
    classes = cut(classes.select("cid", "x.d", "x.th", "m", "n", "low", "high"))
    links = _met(_by_keys(classes), classes, docs, n, percent)
    roots = cut(components(links))
    n_roots = told(roots)
    open_ = _candidates(rows, classes, roots, n_roots, percent)
    # classes that may be linked with others, by the groups that these make
    ends = _rooted(_rooted(open_, roots, n_roots, "a", "ra"), roots, n_roots, "b", "rb").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    groups = cut(components(ends))
    members = _rooted(open_.select(F.explode(F.array("a", "b")).alias("cid")).distinct().join(classes.select("cid", "n"), "cid"), roots, n_roots, "cid", "root")
    members = cut(_rooted(members, groups, told(groups), "root", "g").select("g", "cid", "n", "root"))
    more = _met(_blocks(members, F.col("n")), classes, docs, n, percent)
    # roots of roots: links that were found last connect what the first ones did
    ends = _rooted(_rooted(more, roots, n_roots, "a", "ra"), roots, n_roots, "b", "rb").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    last = cut(components(ends))
    firsts = roots.select("node", F.col("root").alias("first")).union(last.select("node", F.col("node").alias("first"))).distinct()
    out = cut(_rooted(firsts, last, told(last), "first", "root").select("node", "root"))
    drop(classes, links, roots, open_, groups, members, more, last)
    return out


def join(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, one row for each row of ``docs``.

    Documents are linked if 100 * intersection >= percent * union of their sets of word ``n``-grams; component_id is
    the smallest doc_id of all that links reach.
    """
    out = _joined(docs, n, percent)
    return out.select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def _joined(docs: DataFrame, n: int, percent: int) -> DataFrame:
    """doc_id, th, n_shingles, root, component_id; ``root`` tells components apart and is null, as component_id is, of empty sets."""
    docs = docs.select("doc_id", "text")
    rows = cut(_fronts(docs, n, percent))
    found = _class_roots(rows, docs, n, percent)
    slim = cut(rows.select("d", "th", "cid", "n"))
    drop(rows)
    own = F.when(F.col("d") != _NO_ID, F.col("d"))
    rooted = _rooted(slim, found, told(found), "cid", "root").withColumn("root", F.when(F.col("n") > 0, F.col("root")))
    # a component of one row has its name from there
    names = cut(rooted.where("n > 0").groupBy("root").agg(F.min(own).alias("name"), F.count("*").alias("m")).where("m > 1").select("root", "name"))
    out = rooted.join(_small(names, told(names)), "root", "left")
    return out.select(own.alias("doc_id"), "th", F.col("n").alias("n_shingles"), "root", F.when(F.col("n") > 0, F.coalesce("name", own)).alias("component_id"))


def dedup(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """One row of ``docs`` of each component, that of the smallest doc_id; rows alike in id and text count as one.

    Where several texts of a component have that id, the one of the least hash stays. An id stays more than once if its
    texts are no near copies of each other.
    """
    rows = cut(_joined(docs, n, percent).where("doc_id IS NOT NULL").select("doc_id", "th", "root", (F.col("n_shingles") > 0).alias("some"), "component_id"))
    first = cut(rows.where("NOT some OR doc_id = component_id").groupBy("root", "doc_id", "th").agg(F.count("*").alias("m")), repeated=F.count_if(F.col("m") > 1))
    several = first.where("root IS NOT NULL").groupBy("root", "doc_id").agg(F.min("th").alias("least"), F.count("*").alias("m")).where("m > 1").select("root", "doc_id", "least")
    several = cut(several)
    others = first.join(_small(several, told(several)), ["root", "doc_id"]).where("th <> least").select("doc_id", "th")
    gone = cut(rows.where("some AND doc_id <> component_id").select("doc_id", "th").union(others).distinct())
    kept = packed(docs.where("doc_id IS NOT NULL"), F.col("doc_id").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"))
    kept = without(kept, gone, told(gone), "doc_id", "th", most=MOST)
    if told(first, "repeated"):  # ids that several rows have
        kept = kept.dropDuplicates(["doc_id", "th"])
    drop(rows, first, several)
    return kept.select("row.*").unionByName(docs.where("doc_id IS NULL"))
