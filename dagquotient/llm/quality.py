"""Quality classifier: histogram gradient-boosted trees over document statistics.

Trees are complete and of one depth, so an ensemble is three arrays (feature, threshold, leaf value) and a batch of
documents walks all of them by array indexing. The labelled sample that the trees are fitted on is bounded
(``SAMPLE`` ids, the smallest by a hash); statistics are taken of whole texts.

A null text counts as empty and is scored as such. Rows with a null label are not learned from. Repeated rows get
equal scores, extra columns stay, but one named ``score`` is replaced; without any usable label every document gets the
score 0.5.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import width

#: Labelled rows that are learned from at most.
SAMPLE = 20_000
_KINDS = np.zeros((256, 9))
for _k, _bytes in enumerate((range(0x41, 0x5B), range(0x61, 0x7B), range(0x30, 0x3A), b" ", b"\n", b".,;:", b"!?", b"#$%&*+/<=>@[\\]^_`{|}~", range(0x80, 0x100))):
    _KINDS[list(_bytes), _k] = 1
NAMES = ["log_bytes", *(f"share_{x}" for x in ("upper", "lower", "digit", "space", "newline", "stop", "shout", "symbol", "high")), "byte_entropy", "log_words", "word_len", "word_len_sd", "distinct", "top_word", "top_three", "line_words", "distinct_lines", "repeated_pairs", "longest_word", "letters_only", "capitals", "short_words"]


def statistics(text: str | None) -> list[float]:
    """The numbers of ``NAMES`` for one text, none of which depends on the words of a language."""
    text = text or ""
    raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    counts = np.bincount(raw, minlength=256)
    n = max(1, raw.size)
    share = counts[counts > 0] / n
    words = text.split()
    if not words:
        return [np.log1p(raw.size), *(counts @ _KINDS / n), float(-(share * np.log2(share)).sum()), *[0.0] * 13]
    m = len(words)
    seen = Counter(words)
    lengths = np.fromiter(map(len, words), np.float64, m)
    top = [c for _, c in seen.most_common(3)]
    lines = [x for x in text.split("\n") if x.strip()]
    pairs = len(set(zip(words, words[1:], strict=False)))
    return [
        np.log1p(raw.size), *(counts @ _KINDS / n), float(-(share * np.log2(share)).sum()),
        np.log1p(m), lengths.mean(), lengths.std(), len(seen) / m, top[0] / m, sum(top) / m,
        m / len(lines), len(set(lines)) / len(lines), 1 - pairs / max(1, m - 1), np.log1p(lengths.max()),
        sum(map(str.isalpha, words)) / m, sum(map(str.istitle, words)) / m, float((lengths <= 2).mean()),
    ]


@dataclass
class Forest:
    """``feature`` and ``threshold``: trees x inner nodes in heap order; ``leaf``: trees x leaves."""

    feature: np.ndarray
    threshold: np.ndarray
    leaf: np.ndarray
    base: float

    def score(self, x: np.ndarray) -> np.ndarray:
        depth = int(np.log2(self.leaf.shape[1]))
        trees, rows = np.arange(len(self.leaf))[None, :], np.arange(len(x))[:, None]
        node = np.zeros((len(x), len(self.leaf)), np.int64)
        for _ in range(depth):
            node = 2 * node + 1 + (x[rows, self.feature[trees, node]] > self.threshold[trees, node])
        total = self.base + self.leaf[trees, node - (2**depth - 1)].sum(axis=1)
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 48, ridge: float = 4.0) -> Forest:
    """Boosted logistic loss, level by level, on histograms of quantile-binned features."""
    inner, n, width = 2**depth - 1, len(y), x.shape[1]
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
    mean = (y.sum() + 1) / (n + 2)
    base = float(np.log(mean / (1 - mean)))
    feature, threshold = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf)
    leaf, total = np.zeros((trees, 2**depth)), np.full(n, base)
    for t in range(trees):
        p = 1 / (1 + np.exp(-total))
        grad, hess = y - p, p * (1 - p)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            first, many = 2**level - 1, 2**level
            best = np.full(many, 1e-6)
            for j in range(width):
                key = (node - first) * bins + binned[:, j]
                g, h = (np.bincount(key, v, many * bins).reshape(many, bins).cumsum(axis=1) for v in (grad, hess))
                right_g, right_h = g[:, -1:] - g, h[:, -1:] - h
                gain = g**2 / (h + ridge) + right_g**2 / (right_h + ridge) - g[:, -1:] ** 2 / (h[:, -1:] + ridge)
                gain[:, len(edges[j]) :] = 0
                cut = gain.argmax(axis=1)
                for k in np.flatnonzero(gain[np.arange(many), cut] > best):
                    best[k], feature[t, first + k], threshold[t, first + k] = gain[k, cut[k]], j, edges[j][cut[k]]
            node = 2 * node + 1 + (x[np.arange(n), feature[t, node]] > threshold[t, node])
        at = node - inner
        leaf[t] = rate * np.bincount(at, grad, 2**depth) / (np.bincount(at, hess, 2**depth) + ridge)
        total += leaf[t, at]
    return Forest(feature, threshold, leaf, base)


def bounded_sample(docs: DataFrame, labels: DataFrame, label: str, learn: Column, most: int) -> DataFrame:
    """doc_id, text and y (the label) of ``most`` labelled ids at most, those of the smallest hashes of doc_id.

    Of rows that share an id one text is taken, that of the least hash. Rows are dealt evenly to tasks by id.
    """
    chosen = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & F.coalesce(learn, F.lit(False))).groupBy("doc_id").agg(F.max(label).alias("y"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)  # a top-k: no more than ``most`` rows move
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").repartition(width(docs.sparkSession), "doc_id")
    one = rows.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text", "y")).alias("x"))
    return one.select("doc_id", "x.text", "x.y")


def _stat_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x = [statistics(t) for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("y").cast(pa.float64()), pa.array(x, pa.list_(pa.float64()))], ["y", "x"])


def train(docs: DataFrame, labels: DataFrame, learn: Column, label: str = "quality", most: int = SAMPLE) -> Forest | None:
    """Fitted on labelled rows for which ``learn`` holds; statistics are taken on the executors, ``most`` rows of them."""
    rows = bounded_sample(docs, labels, label, learn, most).select("text", "y").mapInArrow(_stat_rows, "y double, x array<double>").toPandas()
    if rows.empty:
        return None
    x = np.stack(rows["x"].to_numpy())
    y = rows["y"].to_numpy(float)
    order = np.lexsort((*x.T, y))  # as rows come in no fixed order
    return fit(x[order], y[order])


def score(docs: DataFrame, forest: Forest | None) -> DataFrame:
    """The columns of ``docs`` and ``score``: the likelihood of label 1."""
    names = [c for c in docs.columns if c != "score"]
    schema = docs.select(*names).schema.add("score", "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 500):
                part = batch.slice(start, 500)
                out = np.full(part.num_rows, 0.5)
                if forest is not None:
                    out = forest.score(np.array([statistics(t) for t in part.column("text").to_pylist()]))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(out)], [*names, "score"])

    return docs.select(*names).mapInArrow(run, schema)
