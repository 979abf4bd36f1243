from pathlib import Path

import numpy as np

from dagquotient.llm import bpe, common, ngram_join
from tests.llm.test_operators import _components


def held() -> int:
    """MB of this process that are in memory."""
    return int(Path("/proc/self/statm").read_text().split()[1]) * 4096 >> 20


def test_freed_memory_goes_back():
    """Many small pieces with a last one behind them stay with the process until it trims."""
    run = common.trimmed(lambda batches: (x for x in batches))
    parts = [bytes(60_000) for _ in range(4_000)] + [bytes(1000)]
    keep, before = parts.pop(), held()
    del parts
    assert list(run(iter([1, 2]))) == [1, 2]
    assert held() < before - 150 and keep is not None


def test_few_tokens_are_remembered():
    """A worker's memory is the same after many distinct words as after some, and so are the ids."""
    codec = bpe.Codec({bytes([k]): k for k in range(256)}, r"\S+|\s+")
    r = np.random.default_rng(1)
    for _ in range(40):
        text = " ".join(map(str, r.integers(10**9, 10**10, 10_000)))
        assert codec.encode(text).astype(np.uint8).tobytes() == text.encode()
        assert len(codec.known) <= 170_000


def test_driver_builds_only_what_is_linked(spark, monkeypatch):
    """Texts that share n-grams but are hardly linked: no table of a row a text, or of their n-grams, is broadcast."""
    r = np.random.default_rng(8)
    phrases = [" ".join(f"w{12 * k + j}" for j in range(12)) for k in range(800)]
    texts = [" ".join(phrases[k] for k in r.permutation(x)) for x in np.concatenate([r.permutation(800).reshape(100, 8) for _ in range(6)])]
    texts[7], texts[5] = texts[20] + " x", texts[9]
    rows = [(k, t, None) for k, t in enumerate(texts)]
    docs = spark.createDataFrame([x[:2] for x in rows], "doc_id long, text string")
    seen = []
    for module in (common, ngram_join):
        monkeypatch.setattr(module, "small", lambda df, rows, *most, f=module.small: seen.append(rows) or f(df, rows, *most))
    want = _components(rows, 5, 80)
    assert {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in ngram_join.join(docs, 5, 80).collect()} == want
    assert seen and max(seen) < 200
    assert {x["doc_id"] for x in ngram_join.dedup(docs, 5, 80).collect()} == set(range(600)) - {9, 20}
    assert max(seen) < 200


def test_near_copies_beyond_a_broadcast(spark, monkeypatch):
    """Where nothing may be broadcast results are the same, also of repeated rows, repeated ids and rows without an id."""
    r = np.random.default_rng(9)
    texts = [[f"w{x}" for x in r.integers(0, 300, 80)] for _ in range(20)]
    rows = [(k, " ".join(t)) for k, t in enumerate(texts)]
    rows += [(30 + k, " ".join(["y", *t[1:]])) for k, t in enumerate(texts[:8])]
    rows += [rows[3], rows[3], (4, rows[24][1]), (None, rows[5][1]), (None, "a b"), (None, "a b"), (50, None), (50, ""), (51, " "), (51, "a b c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")

    def both():
        join = sorted((x["doc_id"] is None, x["doc_id"] or 0, x["n_shingles"], -1 if x["component_id"] is None else x["component_id"]) for x in ngram_join.join(docs, 5, 80).collect())
        return join, sorted((x["doc_id"] is None, x["doc_id"] or 0, x["text"] or "") for x in ngram_join.dedup(docs, 5, 80).collect())

    want = both()
    monkeypatch.setattr(ngram_join, "MOST", 0)
    got = both()
    assert got == want and len(got[0]) == len(rows)
    assert [x[1] for x in got[1] if not x[0]] == [*range(20), 50, 51, 51] and sum(x[0] for x in got[1]) == 3
    assert [x[3] for x in got[0] if 30 <= x[1] < 38] == list(range(8))
