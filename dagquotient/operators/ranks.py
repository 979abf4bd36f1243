"""Phase 1: rank (longest downward path) and structural hash of every node.

``by_peeling`` sends one message along every edge, in as many rounds as there are ranks. A round with few nodes left
costs as much as one with many, so once nodes, edges and waiting messages that are left fit a bounded task, that task
does all remaining ranks (layer fusion). Of a dense graph the edges may fit as bits, a row a node, where they don't as
rows; a task then does the same on bits. ``by_supersteps`` gives ranks alone: what nodes are told is kept as a number
each, and where few nodes are ready a step climbs several ranks. ``by_relaxation`` repeats a maximum until nothing
changes; ``by_blocks`` sweeps ranges of topological ids, each in one task, and repeats for what still waits for another
block.

A hash is made of the label and the distinct hashes of the children, by the function that Spark calls ``xxhash64``;
nodes that are bisimilar have equal hashes. ``commutative`` hashes take the children's as a count, a sum and an
exclusive or, which are aggregated before the shuffle, so that no array is formed for a hub; ``sorted`` ones take them
one by one in ascending order.
"""

from __future__ import annotations

import struct
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dagquotient.functions.lineage import cut, small
from dagquotient.operators.graph import LabeledDag

#: Rows (nodes, edges, messages) that one task may finish on its own.
FUSE_ROWS = 3_000_000
#: Words of 64 bits that count as one of these rows where edges are held as bits: they take as much memory.
ROW_WORDS = 20
#: Nodes that are ready up to which a superstep climbs several ranks, and nodes and edges that its task then holds.
THIN, STEP_ROWS = 1000, 1_000_000
#: Rows that a recursive query may form (-1: any number).
_RECURSION_ROWS = "spark.sql.cteRecursionRowLimit"


class CyclicGraph(ValueError):
    """Nodes that can't be ranked, as they are on a cycle or above one."""


def hash_of(label: Column, hashes: Column, bits: int = 64) -> Column:
    """The hash of a label and an array of child hashes; ``bits`` under 64 cut it short, to provoke collisions."""
    h = F.xxhash64(label, F.array_sort(F.array_distinct(hashes)))
    return h if bits >= 64 else F.pmod(h, F.lit(2**bits))


#: The low half of a hash, of which sums stay within 64 bits.
_LOW = 2**32 - 1
#: Fixed values of the 64-bit hash function.
_P1, _P2, _P3, _P4, _P5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5


def parts_of(hashes: Column) -> list[Column]:
    """Aggregates that tell a set of child hashes, of which each may come once: count, exclusive or, sum."""
    mixed = F.xxhash64(hashes)
    return [F.count(hashes).alias("size"), F.bit_xor(mixed).alias("x"), F.sum(mixed.bitwiseAND(F.lit(_LOW))).alias("y")]


def hash_of_parts(label: Column, bits: int = 64) -> Column:
    """The commutative hash of a label and the columns that ``parts_of`` gives (null: no children)."""
    h = F.xxhash64(label, *[F.coalesce(F.col(c), F.lit(0).cast("long")) for c in ("size", "x", "y")])
    return h if bits >= 64 else F.pmod(h, F.lit(2**bits))


def local_hash(label: str | None, hashes: set[int], bits: int = 64, combine: str = "sorted") -> int:
    """A node's hash outside Spark, which passes null labels over."""
    import xxhash

    values = sorted(hashes)
    if combine == "commutative":
        mixed = [xxhash.xxh64_intdigest(struct.pack("<q", x), 42) for x in values]
        xor = 0
        for m in mixed:
            xor ^= m
        values = [len(mixed), xor - 2**64 if xor >= 2**63 else xor, sum(m & _LOW for m in mixed)]
    h = 42 if label is None else xxhash.xxh64_intdigest(label.encode(), 42)
    for x in values:
        h = xxhash.xxh64_intdigest(struct.pack("<q", x), h)
    h = h - 2**64 if h >= 2**63 else h
    return h if bits >= 64 else h % 2**bits


def _fold(values: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """The hash of one 64-bit number each, from one seed each; unsigned, all at once."""

    def turned(v: np.ndarray, by: int) -> np.ndarray:
        return (v << np.uint64(by)) | (v >> np.uint64(64 - by))

    h = seeds + np.uint64((_P5 + 8) % 2**64)
    h = h ^ (turned(values * np.uint64(_P2), 31) * np.uint64(_P1))
    h = turned(h, 27) * np.uint64(_P1) + np.uint64(_P4)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(_P2)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(_P3)
    return h ^ (h >> np.uint64(32))


def _hashes(seeds: np.ndarray, owner: np.ndarray, child: np.ndarray, bits: int, combine: str) -> np.ndarray:
    """Hashes of nodes from the hashes of their labels and (owner, child hash) rows, repeated ones taken once."""
    order = np.lexsort((child, owner))
    owner, child = owner[order], child[order]
    first = np.ones(len(owner), bool)
    first[1:] = (owner[1:] != owner[:-1]) | (child[1:] != child[:-1])
    owner, child = owner[first], child[first].astype(np.uint64)
    size = np.bincount(owner, minlength=len(seeds))
    begin = np.cumsum(size) - size
    h = seeds
    if combine == "commutative":
        mixed, some = _fold(child, np.full(len(child), 42, np.uint64)), size > 0
        x, y = np.zeros(len(seeds), np.uint64), np.zeros(len(seeds), np.uint64)
        if len(mixed):
            x[some] = np.bitwise_xor.reduceat(mixed, begin[some])
            y[some] = np.add.reduceat(mixed & np.uint64(_LOW), begin[some])
        for part in (size.astype(np.uint64), x, y):
            h = _fold(part, h)
    else:
        h = h.copy()
        for k in range(int(size.max(initial=0))):
            at = np.flatnonzero(size > k)
            h[at] = _fold(child[begin[at] + k], h[at])
    h = h.astype(np.int64)
    return h if bits >= 64 else h % 2**bits


def _finish(table: pa.Table, bits: int, combine: str) -> pa.Table:
    """All ranks of a part of a graph that is closed upwards; rows of kind node, edge or message.

    A rank at a time, with arrays: messages count as children that are known already.
    """
    import pyarrow.compute as pc
    import xxhash

    def rows(kind: str, *names: str) -> list[np.ndarray]:
        some = table.filter(pc.equal(table.column("kind"), kind))
        return [some.column(c).to_numpy(zero_copy_only=False) for c in names]

    named = table.filter(pc.equal(table.column("kind"), "node")).select(["a", "label"]).sort_by("a")
    ids, labels = named.column("a").to_numpy().astype(np.int64), named.column("label").combine_chunks().dictionary_encode()
    n = len(ids)
    seed_of = np.array([xxhash.xxh64_intdigest(x.encode(), 42) for x in labels.dictionary.to_pylist()] + [42], np.uint64)
    code = labels.indices.fill_null(len(seed_of) - 1).to_numpy(zero_copy_only=False).astype(np.int64)
    (parent, child), (to, told, told_rank) = rows("edge", "a", "b"), rows("message", "a", "b", "rank")

    def place(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        values = values.astype(np.int64)
        at = np.searchsorted(ids, values)
        return at, (ids[np.minimum(at, n - 1)] == values) if n else np.zeros(len(values), bool)

    (parent, here), (child, there), (to, mine) = place(parent), place(child), place(to)
    wait = np.bincount(parent[here], minlength=n)
    both = here & there
    parent, child = parent[both], child[both]
    hashes = np.concatenate([np.zeros(n, np.int64), told[mine].astype(np.int64)])
    rank = np.concatenate([np.full(n, -1, np.int64), told_rank[mine].astype(np.int64)])

    def sparse(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(keys, kind="stable")
        return np.concatenate([[0], np.cumsum(np.bincount(keys, minlength=n))]), values[order]

    down = sparse(np.concatenate([parent, to[mine]]), np.concatenate([child, n + np.arange(int(mine.sum()))]))
    up = sparse(child, parent)

    def entries(of: tuple[np.ndarray, np.ndarray], nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position in ``nodes``, value) of what the sparse rows ``nodes`` hold."""
        begin, many = of[0][nodes], of[0][nodes + 1] - of[0][nodes]
        owner = np.repeat(np.arange(len(nodes)), many)
        return owner, of[1][np.arange(len(owner)) + np.repeat(begin - (np.cumsum(many) - many), many)]

    front, done = np.flatnonzero(wait == 0), []
    while len(front):
        owner, below = entries(down, front)
        top = np.full(len(front), -1, np.int64)
        np.maximum.at(top, owner, rank[below])
        rank[front] = top + 1
        hashes[front] = _hashes(seed_of[code[front]], owner, hashes[below], bits, combine)
        done.append(front)
        above, sent = np.unique(entries(up, front)[1], return_counts=True)
        wait[above] -= sent
        front = above[wait[above] == 0]
    at = np.concatenate(done) if done else np.zeros(0, np.int64)
    return pa.table({"node_id": ids[at], "rank": pa.array(rank[at].astype(np.int32)), "label": named.column("label").take(pa.array(at)).combine_chunks(), "hash": hashes[at]})


def _finish_bits(n: int, bits: int):
    """What ``_finish`` does, with edges as ``n`` rows of ``n`` bits: row c has the parents of the node of place c.

    Rows of kind 0 are nodes (place, node_id, label), of kind 1 a few words of bits each (``_WORD``), of kind 2 messages
    (place, rank, hash). A class of children adds to its parents once, whenever its members come.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        ids, names, seeds, told = np.zeros(n, np.int64), np.full(n, None, object), np.full(n, 42, np.uint64), []
        edges, known = np.zeros((n, -(-n // 64)), np.uint64), {None: 42}
        for batch in batches:
            kind = batch.column("kind").to_numpy()
            for k in np.flatnonzero(kind == 1).tolist():
                words = np.frombuffer(batch.column("words")[k].as_buffer(), _WORD)
                np.bitwise_or.at(edges, (words["place"], words["which"]), words["value"])
            place, which, value = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("place", "which", "value"))
            at = np.flatnonzero(kind == 2)
            if len(at):
                told.append((place[at], which[at], value[at]))
            at = np.flatnonzero(kind == 0)
            if len(at):
                ids[place[at]] = value[at]
                for k, label in zip(place[at].tolist(), batch.column("label").take(pa.array(at)).to_pylist(), strict=True):
                    if label not in known:
                        known[label] = xxhash.xxh64_intdigest(label.encode(), 42)
                    names[k], seeds[k] = label, known[label]

        def ones(row: np.ndarray) -> np.ndarray:
            return np.flatnonzero(np.unpackbits(row.view(np.uint8), bitorder="little").view(bool))

        wait, top, rank = np.zeros(64 * edges.shape[1], np.int64), np.full(n, -1, np.int64), np.full(n, -1, np.int64)
        for k in range(0, n, 256):
            wait += np.unpackbits(edges[k : k + 256].view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        wait = wait[:n].copy()
        size, x, y = np.zeros(n, np.int64), np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        to, told_rank, told_hash = (np.concatenate(c) for c in zip(*told, strict=True)) if told else (np.zeros(0, np.int64),) * 3
        order = np.argsort(told_hash, kind="stable")
        to, told_hash = to[order], told_hash[order]
        mixed = _fold(told_hash.astype(np.uint64), np.full(len(to), 42, np.uint64))
        np.add.at(size, to, 1)
        np.bitwise_xor.at(x, to, mixed)
        np.add.at(y, to, mixed & np.uint64(_LOW))
        np.maximum.at(top, to, told_rank[order])
        earlier: dict[int, list[int]] = {}
        front, done, hashes = np.flatnonzero(wait == 0), [], np.zeros(n, np.int64)
        while len(front):
            h = seeds[front]
            for part in (size[front].astype(np.uint64), x[front], y[front]):
                h = _fold(part, h)
            h = h.astype(np.int64) if bits >= 64 else h.astype(np.int64) % 2**bits
            hashes[front], rank[front], wait[front] = h, top[front] + 1, -1
            done.append(front)
            order = np.argsort(h, kind="stable")
            values, begin = np.unique(h[order], return_index=True)
            mixed = _fold(values.astype(np.uint64), np.full(len(values), 42, np.uint64))
            for value, m, members in zip(values.tolist(), mixed, np.split(front[order], begin[1:]), strict=True):
                row = edges[members[0]]
                if len(members) > 1:
                    row = np.bitwise_or.reduce(edges[members])
                    for k in members.tolist():
                        wait[ones(edges[k])] -= 1
                above = ones(row)
                if len(members) == 1:
                    wait[above] -= 1
                top[above] = np.maximum(top[above], rank[members].max())
                if value in earlier:
                    above = ones(row & ~np.bitwise_or.reduce(edges[earlier[value]]))
                low, high = np.searchsorted(told_hash, value, "left"), np.searchsorted(told_hash, value, "right")
                if high > low:
                    above = np.setdiff1d(above, to[low:high])
                earlier.setdefault(value, []).extend(members.tolist())
                size[above] += 1
                x[above] ^= m
                y[above] += m & np.uint64(_LOW)
            front = np.flatnonzero(wait == 0)
        at = np.concatenate(done) if done else np.zeros(0, np.int64)
        for k in range(0, len(at), 10_000):
            some = at[k : k + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(rank[some].astype(np.int32)), pa.array(names[some].tolist(), pa.string()), pa.array(hashes[some])], ["node_id", "rank", "label", "hash"])

    return run


#: A word of 64 bits: the place of a child, which word of its row, and the parents that it tells. Words of a row that is sent, edges sorted at once.
_WORD = np.dtype([("place", "<u4"), ("which", "<u4"), ("value", "<u8")])
_WORDS_A_ROW, _EDGES_AT_ONCE = 256, 2_000_000


def _packed(ids: np.ndarray):
    """Edges between nodes of ``ids`` (sorted) as words of bits; words that other tasks have too are put together later."""

    def pack(parent: list[np.ndarray], child: list[np.ndarray]) -> pa.RecordBatch:
        (p, there), (c, here) = ((np.minimum(np.searchsorted(ids, v), len(ids) - 1), v) for v in map(np.concatenate, (parent, child)))
        both = (ids[p] == there) & (ids[c] == here)
        key = np.sort(c[both] << 32 | p[both])
        word = key >> 6
        begin = np.flatnonzero(np.concatenate([word[:1] == word[:1], word[1:] != word[:-1]]))
        out = np.empty(len(begin), _WORD)
        out["place"], out["which"] = key[begin] >> 32, (key[begin] & (2**32 - 1)) >> 6
        if len(begin):
            out["value"] = np.bitwise_or.reduceat(np.uint64(1) << (key & 63).astype(np.uint64), begin)
        return pa.RecordBatch.from_arrays([pa.array([out[k : k + _WORDS_A_ROW].tobytes() for k in range(0, len(out), _WORDS_A_ROW)], pa.binary())], ["words"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append([batch.column(c).to_numpy() for c in ("parent", "child")])
            size += batch.num_rows
            if size >= _EDGES_AT_ONCE:
                yield pack(*zip(*held, strict=True))
                held, size = [], 0
        if held:
            yield pack(*zip(*held, strict=True))

    return run


def _by_bits(live: DataFrame, edges: DataFrame, inbox: DataFrame | None, n: int, bits: int) -> DataFrame:
    """node_id, rank, label, hash of the ``n`` nodes that are left, their edges put together as bits before one task gets them."""
    nodes = cut(live.select("node_id", "label", (F.row_number().over(Window.orderBy("node_id")) - 1).alias("place")))  # bounded: n rows
    ids = np.sort(nodes.select("node_id").toPandas()["node_id"].to_numpy(np.int64))
    none, no_words = F.lit(None).cast("string").alias("label"), F.lit(None).cast("binary").alias("words")
    words = edges.select("parent", "child").where("parent IS NOT NULL AND child IS NOT NULL").mapInArrow(_packed(ids), "words binary")
    rows = words.select(F.lit(1).alias("kind"), F.lit(0).alias("place"), F.lit(0).alias("which"), F.lit(0).cast("long").alias("value"), none, "words")
    rows = rows.unionByName(nodes.select(F.lit(0).alias("kind"), "place", F.lit(0).alias("which"), F.col("node_id").alias("value"), "label", no_words))
    if inbox is not None:
        rows = rows.unionByName(inbox.join(F.broadcast(nodes.select("node_id", "place")), "node_id").select(F.lit(2).alias("kind"), "place", F.col("rank").alias("which"), F.col("hash").alias("value"), none, no_words))
    return cut(rows.repartition(1).mapInArrow(_finish_bits(n, bits), "node_id long, rank int, label string, hash long"))


def by_peeling(g: LabeledDag, bits: int = 64, fuse_rows: int = FUSE_ROWS, combine: str = "commutative") -> DataFrame:
    """node_id, rank, label, hash (``combine``: commutative or sorted). Raises ``CyclicGraph`` if a node can't be ranked."""
    if combine not in ("commutative", "sorted"):
        raise ValueError(f"unknown hash {combine}")
    done, left = _peel(g, bits, fuse_rows, combine)
    if left is not None:
        some = [r["node_id"] for r in left.select("node_id").limit(5).collect()]
        raise CyclicGraph(f"on or above a cycle: {some}")
    return done


def cyclic_residue(g: LabeledDag) -> DataFrame:
    """node_id of the nodes on a cycle or above one; empty for a DAG."""
    _, left = _peel(g, 64, FUSE_ROWS, "commutative")
    return g.nodes.select("node_id").limit(0) if left is None else left.select("node_id")


def _peel(g: LabeledDag, bits: int, fuse_rows: int, combine: str) -> tuple[DataFrame, DataFrame | None]:
    live = cut(g.nodes.join(g.edges.groupBy(F.col("parent").alias("node_id")).agg(F.count("*").alias("wait")), "node_id", "left").na.fill(0, ["wait"]))
    edges, inbox = g.edges, None
    done = None
    n_live, n_edges, n_inbox = live.count(), edges.count(), 0
    rank = 0
    while n_live:
        rest = None
        if n_live + n_edges + n_inbox <= fuse_rows:
            rows = live.select(F.lit("node").alias("kind"), F.col("node_id").alias("a"), F.lit(None).cast("long").alias("b"), "label", F.lit(None).cast("int").alias("rank"))
            rows = rows.unionByName(edges.select(F.lit("edge").alias("kind"), F.col("parent").alias("a"), F.col("child").alias("b"), F.lit(None).cast("string").alias("label"), F.lit(None).cast("int").alias("rank")))
            if inbox is not None:
                rows = rows.unionByName(inbox.select(F.lit("message").alias("kind"), F.col("node_id").alias("a"), F.col("hash").alias("b"), F.lit(None).cast("string").alias("label"), "rank"))
            rest = cut(rows.groupBy(F.lit(0).alias("one")).applyInArrow(lambda t: _finish(t, bits, combine), "node_id long, rank int, label string, hash long"))
        elif combine == "commutative" and n_inbox <= fuse_rows and n_live * -(-n_live // 64) <= fuse_rows * ROW_WORDS:
            rest = _by_bits(live, edges, inbox, n_live, bits)
        if rest is not None:
            done = rest if done is None else done.unionByName(rest)
            if rest.count() < n_live:
                return done, live.join(rest, "node_id", "left_anti")
            return done, None
        ready = live.where("wait = 0")
        family = (g.edges.select(F.col("parent").alias("node_id"), F.col("child").alias("hash"), F.lit(0).alias("rank")).limit(0) if inbox is None else inbox).groupBy("node_id")
        if combine == "sorted":
            known = family.agg(F.max("rank").alias("top"), F.collect_set("hash").alias("hashes"))
            own = hash_of(F.col("label"), F.coalesce("hashes", F.array().cast("array<long>")), bits)
        else:
            known = family.agg(F.max("rank").alias("top"), *parts_of(F.col("hash")))
            own = hash_of_parts(F.col("label"), bits)
        front = ready.join(known, "node_id", "left").select("node_id", (F.coalesce("top", F.lit(-1)) + 1).cast("int").alias("rank"), "label", own.alias("hash"))
        front = cut(front)
        n_front = front.count()
        if not n_front:
            return done if done is not None else front, live
        done = front if done is None else done.unionByName(front)
        side = small(front.select(F.col("node_id").alias("child"), "rank", "hash"), n_front)
        sent = cut(edges.join(side, "child").select(F.col("parent").alias("node_id"), "rank", "hash"))
        got = sent.groupBy("node_id").agg(F.count("*").alias("got"))
        live = cut(live.where("wait > 0").join(got, "node_id", "left").select("node_id", "label", (F.col("wait") - F.coalesce("got", F.lit(0))).alias("wait")))
        merged = sent if inbox is None else inbox.join(small(front.select("node_id"), n_front), "node_id", "left_anti").unionByName(sent)
        inbox = cut(merged.groupBy("node_id", "hash").agg(F.max("rank").alias("rank")))
        n_live, n_inbox = live.count(), inbox.count()
        n_edges -= sent.count()
        if rank % 4 == 3 or n_live + n_edges + n_inbox <= fuse_rows:  # what is delivered need not be read again
            edges = cut(edges.join(live.select(F.col("node_id").alias("child")), "child", "left_semi"))
        rank += 1
    return done if done is not None else live.select("node_id", F.lit(0).alias("rank"), "label", F.lit(0).cast("long").alias("hash")), None


def _climb(table: pa.Table) -> pa.Table:
    """node_id, rank of what can be ranked among some nodes (a: id, b: children that it waits for, rank: the highest told) and the edges between them."""
    import pyarrow.compute as pc

    def rows(kind: str, *names: str) -> list[np.ndarray]:
        some = table.filter(pc.equal(table.column("kind"), kind))
        return [some.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in names]

    (ids, wait, top), (parent, child) = rows("node", "a", "b", "rank"), rows("edge", "a", "b")
    order = np.argsort(ids)
    ids, wait, top = ids[order], wait[order], top[order]
    parent, child = np.searchsorted(ids, parent), np.searchsorted(ids, child)
    parent = parent[np.argsort(child, kind="stable")]
    begin = np.concatenate([[0], np.cumsum(np.bincount(child, minlength=len(ids)))])
    rank, front = np.full(len(ids), -1, np.int64), np.flatnonzero(wait == 0)
    while len(front):
        rank[front] = top[front] + 1
        many = begin[front + 1] - begin[front]
        above = parent[np.arange(int(many.sum())) + np.repeat(begin[front] - (np.cumsum(many) - many), many)]
        np.maximum.at(top, above, np.repeat(rank[front], many))
        above, sent = np.unique(above, return_counts=True)
        wait[above] -= sent
        front = above[wait[above] == 0]
    at = np.flatnonzero(rank >= 0)
    return pa.table({"node_id": ids[at], "rank": pa.array(rank[at].astype(np.int32))})


def by_supersteps(g: LabeledDag, thin: int = THIN, step_rows: int = STEP_ROWS) -> DataFrame:
    """node_id, rank, without hashes: a node is told how many of its children are done and the highest rank of these.

    A step finishes the nodes that wait for no child. Up to ``thin`` of these don't pay for a round over all edges: then
    one task climbs as far as it can among the nodes that wait for the fewest children, as many of them as have
    ``step_rows`` nodes and edges that wait. The rest is done by later steps. Raises ``CyclicGraph`` as ``by_peeling`` does.
    """
    degree = g.edges.groupBy(F.col("parent").alias("node_id")).agg(F.count("*").alias("wait"))
    live = cut(g.nodes.join(degree, "node_id", "left").select("node_id", F.coalesce("wait", F.lit(0)).alias("wait"), F.lit(-1).alias("top")))
    edges, done, n_live = g.edges, None, live.count()
    n_read = n_live
    while n_live:
        waits = live.groupBy("wait").count().orderBy("wait").collect()  # fewer rows than twice the root of the edges
        if waits[0]["wait"]:
            raise CyclicGraph(f"on or above a cycle: {[r['node_id'] for r in live.select('node_id').limit(5).collect()]}")
        most, held = 0, 0
        for r in waits:
            held += r["count"] * (1 + r["wait"])
            if held > step_rows:
                break
            most = r["wait"]
        if waits[0]["count"] <= thin and most:
            some = cut(live.where(F.col("wait") <= most))
            ids = F.broadcast(some.select("node_id"))  # bounded: ``step_rows``
            between = edges.join(ids.withColumnRenamed("node_id", "parent"), "parent").join(ids.withColumnRenamed("node_id", "child"), "child")
            rows = some.select(F.lit("node").alias("kind"), F.col("node_id").alias("a"), F.col("wait").alias("b"), F.col("top").alias("rank"))
            rows = rows.unionByName(between.select(F.lit("edge").alias("kind"), F.col("parent").alias("a"), F.col("child").alias("b"), F.lit(-1).alias("rank")))
            front = cut(rows.groupBy(F.lit(0).alias("one")).applyInArrow(_climb, "node_id long, rank int"))
        else:
            front = cut(live.where("wait = 0").select("node_id", (F.col("top") + 1).cast("int").alias("rank")))
        n_front = front.count()
        done = front if done is None else done.unionByName(front)
        n_live -= n_front
        if not n_live:
            break
        told = edges.join(small(front.withColumnRenamed("node_id", "child"), n_front), "child").groupBy(F.col("parent").alias("node_id")).agg(F.count("*").alias("got"), F.max("rank").alias("high"))
        left = live.join(small(front.select("node_id"), n_front), "node_id", "left_anti").join(told, "node_id", "left")
        live = cut(left.select("node_id", (F.col("wait") - F.coalesce("got", F.lit(0))).alias("wait"), F.greatest("top", F.coalesce("high", F.lit(-1))).alias("top")))
        if 2 * n_live <= n_read:  # what is delivered need not be read again
            edges = cut(edges.join(small(live.select(F.col("node_id").alias("child")), n_live), "child", "left_semi"))
            n_read = n_live
    return done if done is not None else live.select("node_id", F.lit(0).alias("rank"))


def by_relaxation(g: LabeledDag, max_rounds: int = 10_000) -> DataFrame:
    """node_id, rank, label: ranks grow from 0 until no edge asks for more; every edge is read in every round."""
    now = cut(g.nodes.select("node_id", F.lit(0).alias("rank")))
    for _ in range(max_rounds):
        wanted = g.edges.join(now.withColumnRenamed("node_id", "child"), "child").groupBy(F.col("parent").alias("node_id")).agg((F.max("rank") + 1).alias("wanted"))
        new = cut(now.join(wanted, "node_id", "left").select("node_id", F.greatest("rank", F.coalesce("wanted", F.lit(0))).alias("rank"), (F.coalesce("wanted", F.lit(0)) > F.col("rank")).alias("grew")))
        now = new.select("node_id", "rank")
        if new.where("grew").isEmpty():
            return now.join(g.nodes, "node_id")
    raise CyclicGraph(f"ranks still grow after {max_rounds} rounds")


def _sweep(table: pa.Table, bits: int, combine: str) -> pa.Table:
    """One block: nodes in the order of their ids; what waits for another block stays open."""
    import heapq

    kind, a, b, label, rank = (table.column(c).to_pylist() for c in ("kind", "a", "b", "label", "rank"))
    names, wait, up, queue = {}, {}, defaultdict(list), []
    for k, x, y, name, r in zip(kind, a, b, label, rank, strict=True):
        if k == "node":
            names[x], wait[x] = name, r
        elif k == "edge":
            up[y].append(x)
        else:
            queue.append((x, r, y))
    heapq.heapify(queue)
    out = []
    for x in sorted(names):
        got, top, seen = 0, -1, set()
        while queue and queue[0][0] <= x:
            to, r, h = heapq.heappop(queue)
            if to == x:
                got, top = got + 1, max(top, r)
                seen.add(h)
        if got == wait[x]:
            h = local_hash(names[x], seen, bits, combine)
            out.append((x, top + 1, names[x], h))
            for p in up[x]:
                if p in names:
                    heapq.heappush(queue, (p, top + 1, h))
    columns = list(zip(*out, strict=True)) or [[], [], [], []]
    return pa.table({"node_id": pa.array(columns[0], pa.int64()), "rank": pa.array(columns[1], pa.int32()), "label": pa.array(columns[2], pa.string()), "hash": pa.array(columns[3], pa.int64())})


def by_blocks(g: LabeledDag, n_blocks: int = 8, bits: int = 64, combine: str = "commutative") -> DataFrame:
    """node_id, rank, label, hash for reverse-topological ids: sweeps over ranges of ids until no node waits."""
    if not g.edges.where("child >= parent").isEmpty():
        raise ValueError("ids must put children before parents")
    bounds = g.nodes.agg(F.percentile_approx("node_id", F.array(*[F.lit(k / n_blocks) for k in range(1, n_blocks)] or [F.lit(1.0)]), F.lit(10_000))).first()[0] or []
    block = lambda c: F.size(F.filter(F.array(*[F.lit(x) for x in sorted(set(bounds))]).cast("array<long>"), lambda q: q < F.col(c)))
    degree = g.edges.groupBy(F.col("parent").alias("node_id")).agg(F.count("*").cast("int").alias("wait"))
    nodes = cut(g.nodes.join(degree, "node_id", "left").na.fill(0, ["wait"]).withColumn("block", block("node_id")))
    edges = cut(g.edges.withColumns({"from": block("child"), "to": block("parent")}))
    done, n, total = None, 0, nodes.count()
    while n < total:
        todo = nodes if done is None else nodes.join(done.select("node_id"), "node_id", "left_anti")
        rows = todo.select("block", F.lit("node").alias("kind"), F.col("node_id").alias("a"), F.lit(None).cast("long").alias("b"), "label", F.col("wait").alias("rank"))
        inner = edges.where("`from` = `to`").select(F.col("to").alias("block"), F.lit("edge").alias("kind"), F.col("parent").alias("a"), F.col("child").alias("b"), F.lit(None).cast("string").alias("label"), F.lit(None).cast("int").alias("rank"))
        rows = rows.unionByName(inner)
        if done is not None:
            known = done.select(F.col("node_id").alias("child"), "rank", "hash")
            told = edges.join(known, "child").select(F.col("to").alias("block"), F.lit("message").alias("kind"), F.col("parent").alias("a"), F.col("hash").alias("b"), F.lit(None).cast("string").alias("label"), "rank")
            rows = rows.unionByName(told)
        new = cut(rows.groupBy("block").applyInArrow(lambda t: _sweep(t, bits, combine), "node_id long, rank int, label string, hash long"))
        more = new.count()
        if not more:
            raise CyclicGraph("no block can go on")
        n += more
        done = new if done is None else cut(done.unionByName(new))
    return done if done is not None else nodes.select("node_id", F.lit(0).alias("rank"), "label", F.lit(0).cast("long").alias("hash"))


def by_recursive_sql(g: LabeledDag) -> DataFrame:
    """node_id, rank, label by a recursive query, a row for each path: for trees, chains and small graphs.

    Of Spark's limits on recursion, that on levels (100) holds; that on rows is lifted while the query runs.
    """
    spark = g.nodes.sparkSession
    text = """
      WITH RECURSIVE paths(node_id, steps) AS (
        SELECT node_id, 0 FROM {nodes} UNION ALL
        SELECT e.parent, p.steps + 1 FROM paths p JOIN {edges} e ON e.child = p.node_id)
      SELECT n.node_id, CAST(max(steps) AS INT) AS rank, n.label FROM paths JOIN {nodes} n ON n.node_id = paths.node_id GROUP BY n.node_id, n.label"""
    before = spark.conf.get(_RECURSION_ROWS)
    spark.conf.set(_RECURSION_ROWS, "-1")
    try:
        return cut(spark.sql(text, nodes=g.nodes, edges=g.edges))
    finally:
        spark.conf.set(_RECURSION_ROWS, before)
