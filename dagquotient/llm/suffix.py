"""Suffix-array dedup: passages of ``length`` bytes or more that occur elsewhere, by earlier and later factors as long.

Suffixes of a whole corpus are not sorted at once. Every window of ``length`` bytes has an anchor, the least of the
hashes of its short byte strings; equal windows have equal anchors at equal offsets. So

* each document is cut into contexts, the runs of windows with one anchor (about one in 85 bytes begins one);
* contexts whose anchor occurs once hold nothing repeated; equal contexts collapse into one and a count;
* what is left, different contexts of one anchor, is dealt to tasks by anchor. There suffixes of blocks of contexts in
  corpus order are sorted by doubled prefixes; in suffix order those alike for ``length`` bytes follow each other, and all but
  the earliest of them have an earlier factor of that length, all but the latest a later one;
* texts are dealt out only where a bitmap of the documents that are asked for may hold them;
* an anchor with more contexts than a block should hold has its windows compared by 128-bit hashes, which deals them
  out evenly.

``first="goes"`` marks every copy, ``first="stays"`` all but the earliest (by doc_id, then position). Matches never
cross documents. Nulls count as empty, texts shorter than ``length`` keep everything. Rows alike in id and text count
as different documents in the search and get equal results (with ``first="stays"`` both keep what is first in them).
Extra columns are ignored, an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import among, cut, drop, sieve, small, told

#: Bytes of the strings whose hashes make anchors, bytes of a block of contexts, contexts of an anchor that a
#: block may hold, and windows of a piece of a context.
GRAM, BLOCK, CROWD, RUN = 32, 1 << 20, 3000, 8
#: Bytes from which a text is searched in pieces, and bytes that the windows of a piece begin in.
GIANT, PIECE = 1 << 27, 1 << 26
_NO_ID = -(2**63)
_MIX = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_PLACE = 28  # bits of a position; the rest of a key is hash


def _gram_hashes(raw: np.ndarray) -> np.ndarray:
    h, base, span = _MIX[raw], 0x9E3779B97F4A7C15, 1
    while span < GRAM:
        h = h[:-span] * np.uint64(base) + h[span:]
        base, span = base * base % 2**64, 2 * span
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while 2 * span <= width:
        x, span = np.minimum(x[:-span], x[span:]), 2 * span
    return np.minimum(x[: len(x) - (width - span)], x[width - span :]) if width > span else x


def contexts(raw: np.ndarray, ends: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of concatenated documents: anchor, first window, number of windows and offset of the anchor of each context."""
    empty = np.zeros(0, np.int64)
    if len(raw) < length:
        return empty.astype(np.uint64), empty, empty, empty
    h = _gram_hashes(raw)
    key = (h >> np.uint64(_PLACE) << np.uint64(_PLACE)) | np.arange(len(h), dtype=np.uint64)
    place = (_sliding_min(key, length - GRAM + 1) & np.uint64(2**_PLACE - 1)).astype(np.int64)
    start = np.arange(len(place))
    inside = start + length <= ends[np.searchsorted(ends, start, side="right")]
    change = np.ones(len(place), bool)
    change[1:] = (place[1:] != place[:-1]) | ~inside[:-1]
    first = np.flatnonzero(change & inside)
    # a context ends before the next change or the next window that leaves its document
    bounds = np.flatnonzero(change | ~inside)
    at = np.searchsorted(bounds, first, side="right")
    after = np.append(bounds, len(place))[at]
    return h[place[first]], first, after - first, place[first] - first


def _parts(texts: list[bytes], length: int) -> Iterator[list[tuple[int, int, bytes]]]:
    """(row, offset, bytes) in lots of about a megabyte; a giant text comes in lots of its own.

    Pieces of a giant text overlap by less than a window, so that each of its windows is in one of them.
    """
    lot, size = [], 0
    for row, text in enumerate(texts):
        if len(text) >= GIANT:
            for at in range(0, len(text), PIECE):
                yield [(row, at, text[at : at + PIECE + length - 1])]
            continue
        lot.append((row, 0, text))
        size += len(text)
        if size >= BLOCK:
            yield lot
            lot, size = [], 0
    if lot:
        yield lot


def _long(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def _find(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d, th = (batch.column(k).to_numpy() for k in (0, 1))
            for lot in _parts(batch.column(2).to_pylist(), length):
                whole = b"".join(x[2] for x in lot)
                raw = np.frombuffer(whole, np.uint8)
                ends = np.cumsum([len(x[2]) for x in lot])
                anchor, first, n, offset = contexts(raw, ends, length)
                digest = b"".join(hashlib.blake2b(b"%d %d " % (k, o) + whole[s : s + k - 1 + length], digest_size=16).digest() for s, k, o in zip(first.tolist(), n.tolist(), offset.tolist(), strict=True))
                c = np.frombuffer(digest, np.int64).reshape(-1, 2)
                which = np.searchsorted(ends, first, side="right")
                row = np.array([x[0] for x in lot])[which]
                base = np.array([x[1] for x in lot])[which] - np.concatenate([[0], ends[:-1]])[which]
                yield pa.RecordBatch.from_arrays([_long(anchor), _long(c[:, 0]), _long(c[:, 1]), _long(d[row]), _long(th[row]), pa.array((first + base).astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(offset.astype(np.int32))], ["h", "c1", "c2", "d", "th", "s", "n", "o"])

    return run


def suffix_ranks(text: np.ndarray, depth: int) -> list[tuple[int, np.ndarray]]:
    """(k, rank of every suffix by its first k symbols) for k = 1, 7, 14, 28, ... up to more than half of ``depth``.

    Symbols are below 512, so the first seven fit one number; then lengths double. Suffixes that are alone with their
    rank keep it and are not sorted again.
    """
    n = len(text)
    packed = np.zeros(n, np.int64)
    for k in range(7):
        packed <<= 9
        packed[: max(0, n - k)] += text[k:].astype(np.int64) + 1
    order = np.argsort(packed)
    new = np.concatenate([[True], packed[order][1:] != packed[order][:-1]])
    start = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    rank = np.empty(n, np.int64)
    rank[order] = start  # the rank of a group is the place of its first suffix
    out, k = [(1, text.astype(np.int64)), (7, rank)], 7
    while k < depth:
        alone = new & np.append(new[1:], True)
        at = np.flatnonzero(~alone)
        rank = rank.copy()
        if len(at):
            held = order[at]
            ahead = held + k
            second = np.where(ahead < n, rank[np.minimum(ahead, n - 1)] + 1, 0)
            key = start[at] * (n + 1) + second
            by = np.argsort(key)
            order = order.copy()
            order[at] = held[by]
            key = key[by]
            new = new.copy()
            new[at] = np.concatenate([[True], key[1:] != key[:-1]])
            start = np.maximum.accumulate(np.where(new, np.arange(n), 0))
            rank[order[at]] = start[at]
        k *= 2
        out.append((k, rank))
    return out


def longest_factors(text: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """For each suffix the longest match, as far as ``depth`` symbols, with one that begins earlier, and with a later one.

    In suffix order the best earlier match of a suffix is its previous or its next neighbour that begins earlier.
    """
    ranks = suffix_ranks(text, depth)
    n = len(text)
    order = np.argsort(ranks[-1][1], kind="stable")
    a, b, lcp = order[:-1].copy(), order[1:].copy(), np.zeros(max(0, n - 1), np.int64)
    for k, rank in reversed(ranks):
        for _ in range(6 if k == 1 else 2 if (k, rank) is ranks[-1] else 1):
            ok = (a + k <= n) & (b + k <= n)
            same = np.zeros(len(a), bool)
            same[ok] = rank[a[ok]] == rank[b[ok]]
            lcp += k * same
            a += k * same
            b += k * same
    lcp = np.minimum(lcp, depth)
    out = []
    for position in (order, -order):
        best = np.zeros(n, np.int64)
        for flip in (False, True):
            p = position[::-1] if flip else position
            low = np.concatenate([[0], lcp[::-1] if flip else lcp])[:n]  # match of a place in suffix order with the one before
            to = np.arange(n) - 1
            open_ = np.flatnonzero(to >= 0)
            open_ = open_[p[to[open_]] > p[open_]]
            while len(open_):  # jump over what begins later; whatever it has jumped over is jumped over with it
                over = to[open_]
                low[open_] = np.minimum(low[open_], low[over])
                to[open_] = to[over]
                open_ = open_[(to[open_] >= 0) & (low[open_] > 0)]
                open_ = open_[p[to[open_]] > p[open_]]
            low[to < 0] = 0
            got = np.empty(n, np.int64)
            got[order[::-1] if flip else order] = low
            best = np.maximum(best, got)
        out.append(best)
    return out[0], out[1]


def long_factors(text: np.ndarray, at: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """For each of the ascending places ``at``, at which ``length`` symbols begin: do the same begin at an earlier one, and at a later one?

    That is whether what ``longest_factors`` gives reaches ``length``. Ranks by at least half as many symbols, here and at the
    end, tell suffixes apart as far as that.
    """
    k, rank = suffix_ranks(text, -(-length // 2))[-1]
    key = rank[at] * (len(text) + 1) + rank[at + length - k]
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    before, after = np.zeros(len(at), bool), np.zeros(len(at), bool)
    before[order[1:]], after[order[:-1]] = same, same
    return before, after


def _runs(flags: np.ndarray) -> tuple[list[int], list[int]]:
    """Starts and ends (exclusive) of the runs of true."""
    edge = np.flatnonzero(np.diff(np.concatenate([[False], flags, [False]]).astype(np.int8)))
    return edge[::2].tolist(), edge[1::2].tolist()


def _match(length: int, every: bool):
    """Blocks of whole anchor groups; h, c1, c2 and the runs of repeated windows of each context."""

    def solve(rows: list[dict]) -> pa.RecordBatch:
        rows.sort(key=lambda r: (r["d"], r["th"], r["s"]))
        joined = np.frombuffer(b"\0".join(r["bytes"] for r in rows) + b"\0", np.uint8).astype(np.int16) + 1
        ends = np.cumsum([len(r["bytes"]) + 1 for r in rows])
        joined[ends - 1] = 0
        n = np.array([r["n"] for r in rows])
        last = np.cumsum(n)
        first = ends - np.array([len(r["bytes"]) for r in rows]) - 1
        before, after = long_factors(joined, np.arange(last[-1]) + np.repeat(first - (last - n), n), length)
        match = before | after if every else before
        out = [_runs(match[e - k : e]) for k, e in zip(n.tolist(), last.tolist(), strict=True)]
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in ("h", "c1", "c2")] + [pa.array([x[k] for x in out], pa.list_(pa.int32())) for k in (0, 1)], ["h", "c1", "c2", "starts", "ends"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, last = [], 0, None
        for batch in batches:
            for row in batch.to_pylist():
                if size >= BLOCK and row["h"] != last:
                    yield solve(held)
                    held, size = [], 0
                held.append(row)
                size += len(row["bytes"])
                last = row["h"]
        if held:
            yield solve(held)

    return run


def _pieces(length: int):
    """Every ``RUN`` windows of a context as one row: a hash of all their bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                raw, n = row["bytes"], row["n"]
                # runs are counted from the anchor, so that equal windows of two contexts fall into equal runs
                low = row["o"] % RUN - RUN if row["o"] % RUN else 0
                out = []
                for k in range(low, n, RUN):
                    first, last = max(k, 0), min(k + RUN, n)
                    whole = raw[first : last - 1 + length]
                    place = b"%d %d %d " % (row["o"] - k, first - k, last - first)
                    out.append((first, last, hashlib.blake2b(place + whole, digest_size=16).digest(), raw[first : last - 1 + length]))
                size = len(out)
                w = np.frombuffer(b"".join(x[2] for x in out), np.int64).reshape(-1, 2)
                fixed = [pa.array(np.full(size, row[k]), pa.int32() if k == "s" else pa.int64()) for k in ("h", "c1", "c2", "d", "th", "s")]
                yield pa.RecordBatch.from_arrays([*fixed, pa.array([x[0] for x in out], pa.int32()), pa.array([x[1] for x in out], pa.int32()), _long(w[:, 0]), _long(w[:, 1]), pa.array([x[3] for x in out], pa.binary())], ["h", "c1", "c2", "d", "th", "s", "a", "b", "p1", "p2", "bytes"])

    return run


def _windows(length: int):
    """The windows of the given pieces, one row each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                raw, n = row["bytes"], row["b"] - row["a"]
                w = np.frombuffer(b"".join(hashlib.blake2b(raw[k : k + length], digest_size=16).digest() for k in range(n)), np.int64).reshape(-1, 2)
                fixed = [pa.array(np.full(n, row[k]), pa.int32() if k == "s" else pa.int64()) for k in ("h", "c1", "c2", "d", "th", "s")]
                yield pa.RecordBatch.from_arrays([*fixed, pa.array(np.arange(row["a"], row["b"], dtype=np.int32)), _long(w[:, 0]), _long(w[:, 1]), pa.array(np.full(n, row["times"]), pa.int64())], ["h", "c1", "c2", "d", "th", "s", "k", "w1", "w2", "times"])

    return run


def _crowded(texts: DataFrame, length: int, every: bool) -> DataFrame:
    """h, c1, c2, starts, ends for anchors of very many contexts, by hashes of pieces and then of windows.

    Equal pieces become one, with a count: all windows of a piece that several contexts have are repeated. What is
    left, one piece of each kind, is taken apart into windows.
    """
    key, at = ["h", "c1", "c2"], F.struct("d", "th", "s")
    pieces = cut(texts.mapInArrow(_pieces(length), "h long, c1 long, c2 long, d long, th long, s int, a int, b int, p1 long, p2 long, bytes binary"))
    kinds = cut(pieces.groupBy("h", "p1", "p2").agg(F.count("*").alias("times"), F.min(at).alias("first")))
    one = pieces.join(kinds, ["h", "p1", "p2"]).where(at == F.col("first"))
    windows = cut(one.mapInArrow(_windows(length), "h long, c1 long, c2 long, d long, th long, s int, k int, w1 long, w2 long, times long"))
    again = cut(windows.groupBy("h", "w1", "w2").agg(F.sum("times").alias("all"), F.min(at).alias("first")).where("all > 1"))
    hits = windows.join(again, ["h", "w1", "w2"]).where(F.lit(every) | (at != F.col("first"))).select(*key, F.col("k").alias("a"), (F.col("k") + 1).alias("b"))
    copies = pieces.join(kinds.where("times > 1"), ["h", "p1", "p2"]).where(F.lit(every) | (at != F.col("first"))).select(*key, "a", "b")
    found = hits.union(copies).groupBy(*key).agg(F.collect_set(F.struct("a", "b")).alias("x"))
    return found.select(*key, F.col("x.a").alias("starts"), F.col("x.b").alias("ends"))


def _alike(texts: DataFrame) -> DataFrame:
    """Contexts that share half a window's reach beside the anchor, on either side, with another of their anchor.

    Two contexts with a window in common do: of its bytes beside the anchor at least half are on one side.
    """
    out = texts
    for side in ("left", "right"):
        pair = cut(texts.where(F.col(side).isNotNull()).groupBy("h", side).agg(F.count("*").alias("n")).where("n > 1").select("h", side, F.lit(True).alias(f"has_{side}")))
        out = out.join(small(pair, pair.count()), ["h", side], "left")
    return cut(out.where("has_left OR has_right").drop("left", "right", "has_left", "has_right"))


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The bytes of the wanted contexts of each text."""
    for batch in batches:
        for raw, wanted in zip(batch.column("raw"), batch.column("wanted").to_pylist(), strict=True):
            text = memoryview(raw.as_buffer())
            for x in wanted:
                own = x["bytes"] = bytes(text[x["s"] : x["s"] + x["size"]])
                at, end = x["o"] - x["side"], x["o"] + GRAM
                x["left"] = _short_hash(own[at : x["o"]]) if at >= 0 else None
                x["right"] = _short_hash(own[end : end + x["side"]]) if end + x["side"] <= len(own) else None
            yield pa.RecordBatch.from_pylist(wanted, schema=_WANTED)


def _short_hash(part: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(part, digest_size=8).digest(), "little", signed=True)


_WANTED = pa.schema([(k, pa.int64()) for k in ("h", "c1", "c2", "d", "th", "left", "right")] + [("s", pa.int32()), ("n", pa.int32()), ("o", pa.int32()), ("bytes", pa.binary())])


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce("text", F.lit(""))
    return docs.select("doc_id", "text").select("doc_id", F.coalesce("doc_id", F.lit(_NO_ID)).alias("d"), F.xxhash64(text).alias("th"), F.encode(text, "UTF-8").alias("raw"))


def repeats(docs: DataFrame, length: int = 200, first: str = "goes") -> DataFrame:
    """d, th, s, e: byte ranges of documents that are covered by repeated strings (they may overlap)."""
    return _repeats(docs, length, first)[0]


def _repeats(docs: DataFrame, length: int, first: str) -> tuple[DataFrame, list[DataFrame]]:
    """What ``repeats`` gives, and the tables that it is read from."""
    if length < 2 * GRAM:
        raise ValueError(f"length must be {2 * GRAM} or more")
    every = first == "goes"
    keyed = _keyed(docs)
    every_one = cut(keyed.select("d", "th", "raw").where(F.octet_length("raw") >= length).mapInArrow(_find(length), "h long, c1 long, c2 long, d long, th long, s int, n int, o int"))
    shared = cut(every_one.groupBy("h").agg(F.count("*").alias("times")).where("times > 1").select("h"))
    found = cut(among(every_one, shared, told(shared), "h"))
    drop(every_one, shared)
    key = ["h", "c1", "c2"]
    kinds = cut(found.groupBy(*key).agg(F.count("*").alias("times"), F.min(F.struct("d", "th", "s")).alias("at"), F.first("n").alias("n"), F.first("o").alias("o")))
    anchors = cut(kinds.groupBy("h").agg(F.count("*").alias("kinds"), F.min("times").alias("least")).where((F.col("kinds") > 1) & ((F.col("least") < 2) | F.lit(not every))).select("h"))
    open_ = among(kinds, anchors, told(anchors), "h")
    open_ = cut(open_.select(*key, "at.d", "at.th", "at.s", "n", "o", (F.col("n") + (length - 1)).alias("size"), F.lit(-(-(length - GRAM) // 2)).alias("side")))
    wanted = open_.groupBy("d", "th").agg(F.collect_list(F.struct(*key, "d", "th", "s", "n", "o", "size", "side")).alias("wanted"))
    n_open = told(open_)
    asked = sieve(open_, n_open, "d", "th")(keyed.select("d", "th", "raw")).where("may").drop("may")
    texts = asked.join(wanted, ["d", "th"]).mapInArrow(_cut_out, "h long, c1 long, c2 long, d long, th long, left long, right long, s int, n int, o int, bytes binary")
    texts = cut(texts)
    if texts.count() > n_open:  # repeated rows give the bytes of a context several times: one row of them is enough
        texts = texts.dropDuplicates([*key])
    whole_texts, texts = texts, _alike(texts)
    drop(whole_texts, anchors, open_)
    crowds = cut(texts.groupBy("h").agg(F.count("*").alias("kinds")).where(F.col("kinds") > CROWD).select("h"))
    n_crowds = crowds.count()
    schema = "h long, c1 long, c2 long, starts array<int>, ends array<int>"
    solved = texts.join(small(crowds, n_crowds), "h", "left_anti").repartition("h").sortWithinPartitions("h").mapInArrow(_match(length, every), schema)
    if n_crowds:
        solved = solved.union(_crowded(texts.join(small(crowds, n_crowds), "h", "left_semi"), length, every))
    solved = cut(solved)
    drop(texts, crowds)
    parts = solved.select(*key, F.explode(F.arrays_zip("starts", "ends")).alias("x")).select(*key, F.col("x.starts").alias("a"), F.col("x.ends").alias("b"))
    parts = cut(parts)
    inside = found.select(*key, "d", "th", "s").join(parts, key)
    if not every:
        earliest = kinds.select(*key, "at")
        inside = inside.join(earliest, key).where(F.struct("d", "th", "s") == F.col("at"))
    inside = inside.select("d", "th", (F.col("s") + F.col("a")).alias("s"), (F.col("s") + F.col("b") + (length - 1)).alias("e"))
    whole = cut(kinds.where("times > 1").select(*key, "at"))
    copies = found.join(whole, key).where(F.lit(every) | (F.struct("d", "th", "s") != F.col("at")))
    return inside.union(copies.select("d", "th", "s", (F.col("s") + F.col("n") + (length - 1)).alias("e"))), [found, kinds, solved, parts, whole]


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, kept, starts, ends, size = batch.column("doc_id"), [], [], [], []
        for raw, ranges in zip(batch.column("raw"), batch.column("ranges"), strict=True):
            text = raw.as_py()
            a, b = [], []
            if ranges.is_valid:
                r = np.array([(x["s"], x["e"]) for x in ranges.as_py()], np.int64)
                edge = np.zeros(len(text) + 1, np.int32)
                np.add.at(edge, r[:, 0], 1)
                np.add.at(edge, r[:, 1], -1)
                gone = np.cumsum(edge[:-1]) > 0
                a, b = _runs(gone)
            size.append(len(text))
            kept.append(b"".join(text[i:j] for i, j in zip([0, *b], [*a, len(text)], strict=True)))
            starts.append(a)
            ends.append(b)
        yield pa.RecordBatch.from_arrays([ids, pa.array(size, pa.int64()), pa.array(starts, pa.list_(pa.int32())), pa.array(ends, pa.list_(pa.int32())), pa.array(kept, pa.binary())], ["doc_id", "n_bytes", "starts", "ends", "kept"])


def dedup(docs: DataFrame, length: int = 200, first: str = "goes") -> DataFrame:
    """doc_id, n_bytes, starts, ends (of the removed runs), kept (the remaining bytes), a row for each row of ``docs``."""
    found, tables = _repeats(docs, length, first)
    ranges = cut(found.groupBy("d", "th").agg(F.collect_set(F.struct("s", "e")).alias("ranges")))
    drop(*tables)
    marked = sieve(ranges, told(ranges), "d", "th")(_keyed(docs))
    rows = marked.where("may").join(ranges, ["d", "th"], "left").select("doc_id", "raw", "ranges")
    rows = rows.union(marked.where("NOT may").select("doc_id", "raw", F.lit(None).cast(ranges.schema["ranges"].dataType).alias("ranges")))
    return rows.mapInArrow(_remove, "doc_id long, n_bytes long, starts array<int>, ends array<int>, kept binary")
