"""Byte-level BPE by a sentencepiece model that is written straight from a rank file.

Every byte becomes one printable character, every vocabulary entry a piece scored by its negative rank, and
normalisation is the identity; sentencepiece then merges the adjacent pair of lowest rank first, which is what
byte-level BPE does. A text is split by the tokenizer's pattern, each match is encoded on its own, and ids are
decoded by the inverse table.

Nulls count as empty texts and give no ids. Repeated rows give repeated rows, extra columns are ignored, an empty
table gives an empty table, and texts of any length are encoded whole.
"""

from __future__ import annotations

import base64
import hashlib
import struct
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from dagquotient.llm.common import trimmed

#: Rows that are encoded together.
STEP = 200
KINDS = {"int64": "long", "string": "string", "binary": "binary", "list<item: int32>": "array<int>"}
#: Distinct pre-tokens that a worker remembers before it starts anew with its next lot, however many that has.
CACHE = 150_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def byte_chars() -> list[str]:
    """A printable character for each byte: itself where Latin-1 prints it, else one from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, spare = [""] * 256, 0x100
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b], spare = chr(spare), spare + 1
    return out


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 0x7F:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: int | bytes | float) -> bytes:
    """One protobuf field: varint, length-delimited or 32-bit float by the type of the value."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def sentencepiece_model(ranks: dict[bytes, int]) -> bytes:
    """A serialised BPE model whose piece ``rank + 1`` is the entry of that rank; piece 0 stands for unknown."""
    chars = byte_chars()
    order = sorted(ranks.items(), key=lambda x: x[1])
    if [r for _, r in order] != list(range(len(order))):
        raise ValueError("ranks must be 0, 1, 2, ...")
    out = [_field(1, _field(1, b"<unk>") + _field(2, 0.0) + _field(3, 2))]
    for token, rank in order:
        piece = "".join(chars[b] for b in token).encode()
        out.append(_field(1, _field(1, piece) + _field(2, -float(rank)) + _field(3, 1)))
    none = (1 << 64) - 1  # -1 as a varint
    out.append(_field(2, _field(3, 2) + _field(4, len(order) + 1) + _field(40, 0) + b"".join(_field(n, none) for n in (41, 42, 43))))
    out.append(_field(3, _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)))
    return b"".join(out)


class Codec:
    """Encodes and decodes texts; one lives in each Python worker."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex
        import sentencepiece

        self.split = regex.compile(pattern).findall
        self.model = sentencepiece.SentencePieceProcessor(model_proto=sentencepiece_model(ranks))
        self.ranks = ranks
        self.pieces = [t for t, _ in sorted(ranks.items(), key=lambda x: x[1])]
        self.chars = byte_chars()
        self.known: dict[str, bytes] = {}

    def _learn(self, new: list[str]) -> None:
        """Remember the ids of ``new`` pre-tokens: an entry of the vocabulary is its own token, the rest get merged."""
        hard = []
        for token in new:
            if (whole := self.ranks.get(token.encode())) is None:
                hard.append(token)
            else:
                self.known[token] = struct.pack("<I", whole)
        if hard:
            found = self.model.encode(["".join(map(self.chars.__getitem__, token.encode())) for token in hard], num_threads=1)
            raw, at = (np.fromiter(chain.from_iterable(found), dtype="<u4") - np.uint32(1)).tobytes(), 0
            for token, ids in zip(hard, found, strict=True):
                self.known[token] = raw[at : (at := at + 4 * len(ids))]

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """Of each text, the ids as little-endian unsigned 32-bit integers."""
        tokens = [self.split(text) for text in texts]
        if len(self.known) > CACHE:
            self.known.clear()
        if new := set().union(*tokens).difference(self.known):
            self._learn(list(new))
        return [b"".join(map(self.known.__getitem__, x)) for x in tokens]

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(self.encode_many([text])[0], dtype="<u4")

    def decode(self, ids) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids.tolist() if isinstance(ids, np.ndarray) else ids))


_codecs: dict[tuple[int, str], Codec] = {}


def _codec(ranks: dict[bytes, int], pattern: str) -> Codec:
    """The codec of this worker process, which later tasks in it use again."""
    key = (hash(tuple(ranks.items())), pattern)
    if key not in _codecs:
        _codecs.clear()
        _codecs[key] = Codec(ranks, pattern)
    return _codecs[key]


def _over(df: DataFrame, ranks_path: str, pattern: str, names: list[str], kinds: list[pa.DataType], rows) -> DataFrame:
    """``rows(codec, ids, values)`` over the two columns of ``df``, a few hundred rows or some megabytes at a time."""
    vocabulary = df.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))  # of a fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(vocabulary.value, pattern)
        for batch in batches:
            for start in range(0, batch.num_rows, STEP):
                ids, values = (batch.column(k).slice(start, STEP).to_pylist() for k in (0, 1))
                columns = zip(*rows(codec, ids, values), strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(columns, kinds, strict=True)], names)

    return df.mapInArrow(trimmed(run), ", ".join(f"{n} {KINDS[str(k)]}" for n, k in zip(names, kinds, strict=True)))


def encode(docs: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids: the ids of each whole text."""

    def rows(codec, ids, texts):
        found = [np.frombuffer(raw, dtype="<u4").astype(np.int32) for raw in codec.encode_many([t or "" for t in texts])]
        return [(i, len(x), x) for i, x in zip(ids, found, strict=True)]

    return _over(docs.select("doc_id", "text"), ranks_path, pattern, ["doc_id", "n_tokens", "ids"], [pa.int64(), pa.int64(), pa.list_(pa.int32())], rows)


def decode(encoded: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """doc_id, bytes: the bytes that the ids stand for; null ids give no bytes."""

    def rows(codec, ids, coded):
        return [(i, codec.decode(x or [])) for i, x in zip(ids, coded, strict=True)]

    return _over(encoded.select("doc_id", "ids"), ranks_path, pattern, ["doc_id", "bytes"], [pa.int64(), pa.binary()], rows)


def round_trip(docs: DataFrame, ranks_path: str, pattern: str, keep_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids): each text encoded and decoded again, as digests."""

    def rows(codec, ids, texts):
        out = []
        for i, raw in zip(ids, codec.encode_many([t or "" for t in texts]), strict=True):
            found = np.frombuffer(raw, dtype="<u4")
            row = (i, len(found), hashlib.sha256(raw).hexdigest(), hashlib.sha256(codec.decode(found)).hexdigest())
            out.append((*row, found.astype(np.int32)) if keep_ids else row)
        return out

    names, kinds = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"], [pa.int64(), pa.int64(), pa.string(), pa.string()]
    return _over(docs.select("doc_id", "text"), ranks_path, pattern, names + ["ids"] * keep_ids, kinds + [pa.list_(pa.int32())] * keep_ids, rows)
