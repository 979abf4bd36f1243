"""Toxicity: a linear classifier over words and word beginnings, regularised by counterfactual sentences.

Each labelled sentence that names a group gets counterparts in which the name is swapped for other groups' names,
and the loss adds the squared difference of the two scores: what a group is called may not move a score, so neutral
mentions of groups that toxic texts often name aren't taken for toxic.

The labelled sample is bounded (``SAMPLE`` rows, the smallest by a hash of their id), and so is the number of
features; every text is scored whole. A null text counts as empty. Rows with a null label are not learned from.
Repeated rows get equal scores, extra columns are ignored; without any usable label every score is 0.5.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagquotient.llm.common import cut
from dagquotient.llm.quality import bounded_sample

#: Labelled rows that are learned from at most, features kept, and the least chi-squared of one.
SAMPLE, FEATURES, LEAST = 20_000, 3_000, 15.0
#: Names of groups, by what can stand for what; they need not occur in the sample.
IDENTITIES = (
    ("women", "men", "girls", "boys", "mothers", "fathers"),
    ("woman", "man", "girl", "boy", "mother", "father"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("gay", "lesbian", "straight", "bisexual", "transgender", "queer"),
    ("black", "white", "asian", "african", "latino", "arab"),
    ("immigrants", "refugees", "foreigners", "natives", "migrants", "citizens"),
    ("mexican", "chinese", "indian", "american", "german", "french"),
    ("old", "young", "elderly", "disabled", "blind", "deaf"),
    ("frauen", "männer", "mujeres", "hombres", "femmes", "hommes"),
)
_others = {w: [x for x in group if x != w] for group in IDENTITIES for w in group}
_words = re.compile(r"[^\W\d_]+").findall


def features(text: str | None) -> set[str]:
    """The distinct words of a text, with their beginnings of four and five letters."""
    words = set(_words((text or "").lower()))
    return words | {w[:4] + "-" for w in words if len(w) > 4} | {w[:5] + "-" for w in words if len(w) > 5}


def swapped(text: str, most: int = 3) -> list[tuple[str, str]]:
    """Pairs of a sentence that names a group and the sentence with another group's name in its place."""
    out = []
    for sentence in re.split(r"[.!?\n]+", text.lower()):
        words = _words(sentence)
        for name in dict.fromkeys(w for w in words if w in _others):
            out += [(sentence, re.sub(rf"\b{re.escape(name)}\b", other, sentence)) for other in _others[name][:most]]
    return out


@dataclass
class Model:
    index: dict[str, int]
    weight: np.ndarray
    base: float
    names: frozenset[str] = field(init=False)

    def __post_init__(self) -> None:
        self.names = frozenset(self.index)

    def logit(self, text: str | None) -> float:
        return self.base + sum(self.weight[self.index[f]] for f in self.names.intersection(features(text)))

    def score(self, texts: list[str | None]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip([self.logit(t) for t in texts], -30, 30)))


def _ranked(names: list[str], toxic: np.ndarray, clean: np.ndarray, n1: float, n0: float, most: int, least: float) -> list[str]:
    """The ``most`` features of the largest chi-squared against the label, of ``least`` or more, that toxic texts have
    at least twice as often as others (the lack of ordinary words is no sign), and all names of groups."""
    seen = toxic + clean
    expected = seen * n1 / (n1 + n0)
    chi = (toxic - expected) ** 2 / np.maximum(expected, 1e-9)
    good = (seen >= 5) & (chi >= least) & (toxic * n0 >= 2 * clean * n1)
    order = sorted(np.flatnonzero(good), key=lambda i: (-chi[i], names[i]))[:most]
    chosen = [names[i] for i in order]
    known = set(chosen)
    return chosen + [w for w in sorted(_others) if w not in known]


def _descend(rows: list[np.ndarray], y: np.ndarray, pairs: list[tuple[np.ndarray, np.ndarray]], times: np.ndarray, k: int, ridge: float = 0.05, fairness: float = 4.0, steps: int = 400, rate: float = 0.1) -> tuple[np.ndarray, float]:
    """Logistic loss + ridge + ``fairness`` times the mean squared score change of swapped sentences, by Adam.

    Each of the ``pairs`` stands for ``times`` swapped sentences.
    """

    def flat(bags: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return np.repeat(np.arange(len(bags)), [len(b) for b in bags]), np.concatenate([*bags, np.zeros(0, np.int64)]).astype(np.int64)

    row, col = flat(rows)
    left, right = flat([p[0] for p in pairs]), flat([p[1] for p in pairs])
    m, n = len(pairs), len(y)
    swaps = times.sum()
    w, base = np.zeros(k), float(np.log((y.sum() + 1) / (n - y.sum() + 1)))
    mean, square, base_mean, base_square = np.zeros(k), np.zeros(k), 0.0, 0.0
    for step in range(1, steps + 1):
        p = 1 / (1 + np.exp(-np.clip(base + np.bincount(row, w[col], n), -30, 30)))
        change = times * (np.bincount(left[0], w[left[1]], m) - np.bincount(right[0], w[right[1]], m))
        grad = np.bincount(col, (p - y)[row], k) / n + ridge * w / n
        grad += 2 * fairness / swaps * (np.bincount(left[1], change[left[0]], k) - np.bincount(right[1], change[right[0]], k))
        slope = float((p - y).mean())
        mean, square = 0.9 * mean + 0.1 * grad, 0.999 * square + 0.001 * grad**2
        base_mean, base_square = 0.9 * base_mean + 0.1 * slope, 0.999 * base_square + 0.001 * slope**2
        w -= rate * (mean / (1 - 0.9**step)) / (np.sqrt(square / (1 - 0.999**step)) + 1e-8)
        base -= rate * (base_mean / (1 - 0.9**step)) / (np.sqrt(base_square / (1 - 0.999**step)) + 1e-8)
    return w, base


#: Pairs of bare names, so that groups count alike whether the sample names them or not.
_BARE = [(w, o) for w in sorted(_others) for o in _others[w][:3]]


def train(docs: DataFrame, labels: DataFrame, learn: Column, label: str = "toxic", most: int = SAMPLE, fairness: float = 4.0) -> Model | None:
    """Fitted on at most ``most`` labelled documents for which ``learn`` holds; ``fairness`` weighs the swapped sentences.

    Features are counted on the executors; to the driver go the chosen ones, and of each text the numbers of those
    that it has. All sentences of a text that name a group are swapped; to the driver go only the numbers in which a
    sentence and its counterpart differ, and how many unlike pairs differ in these.
    """
    sample = cut(bounded_sample(docs, labels, label, learn, most).select("text", F.col("y").cast("double").alias("y")))

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text, y in zip(batch.column("text").to_pylist(), batch.column("y"), strict=True):
                found = sorted(features(text))
                yield pa.RecordBatch.from_arrays([pa.array(found, pa.string()), pa.array(np.full(len(found), y.as_py()))], ["f", "y"])

    n, n1 = sample.agg(F.count("*"), F.sum("y")).first()
    if not n:
        return None
    n1, n0 = max(1.0, n1), max(1.0, n - n1)
    counts = sample.mapInArrow(each, "f string, y double").groupBy("f").agg(F.sum("y").alias("a"), F.sum(1 - F.col("y")).alias("b")).where("a + b >= 5")
    expected = (F.col("a") + F.col("b")) * n1 / (n1 + n0)
    chi = F.pow(F.col("a") - expected, 2) / expected
    counts = counts.where(F.col("a") * n0 >= 2 * F.col("b") * n1).orderBy(chi.desc(), "f").limit(FEATURES).collect()
    index = {f: i for i, f in enumerate(_ranked([r["f"] for r in counts], np.array([r["a"] for r in counts], float), np.array([r["b"] for r in counts], float), n1, n0, FEATURES, LEAST))}

    def numbers(text: str | None) -> list[int]:
        return sorted(index[f] for f in features(text) if f in index)

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for t, y in zip(batch.column("text").to_pylist(), batch.column("y").to_pylist(), strict=True):
                swaps = dict.fromkeys((tuple(numbers(a)), tuple(numbers(b))) for a, b in swapped(t or ""))
                out.append({"y": y, "own": numbers(t), "swaps": [{"a": a, "b": b} for a, b in swaps]})
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=_CODED)

    found = cut(sample.mapInArrow(coded, "y double, own array<int>, swaps array<struct<a: array<int>, b: array<int>>>"))
    rows = sorted((r["y"], tuple(r["own"])) for r in found.select("y", "own").toLocalIterator())
    bare = docs.sparkSession.createDataFrame([(numbers(a), numbers(b)) for a, b in _BARE], "a array<int>, b array<int>")
    unlike = found.select(F.explode("swaps").alias("x")).select("x.a", "x.b").union(bare).distinct()
    unlike = unlike.groupBy(F.array_except("a", "b").alias("a"), F.array_except("b", "a").alias("b")).agg(F.count("*").alias("n"))
    swaps = sorted((tuple(r["a"]), tuple(r["b"]), r["n"]) for r in unlike.toLocalIterator())
    w, base = _descend([np.array(r[1], np.int64) for r in rows], np.array([r[0] for r in rows]), [(np.array(a, np.int64), np.array(b, np.int64)) for a, b, _ in swaps], np.array([n for *_, n in swaps]), len(index), fairness=fairness)
    return Model(index, w, base)


_CODED = pa.schema([("y", pa.float64()), ("own", pa.list_(pa.int32())), ("swaps", pa.list_(pa.struct([("a", pa.list_(pa.int32())), ("b", pa.list_(pa.int32()))])))])


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id and ``score``: the likelihood of being toxic."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 500):
                part = batch.slice(start, 500)
                texts = part.column(1).to_pylist()
                out = np.full(len(texts), 0.5) if model is None else model.score(texts)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out)], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")
