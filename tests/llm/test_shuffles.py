import numpy as np
from pyspark.sql import functions as F

from dagquotient.llm import common, ngram_join, suffix


def test_long_factors():
    r = np.random.default_rng(4)
    for n in (70, 140, 400):
        t = r.integers(0, 2, n)
        t[n // 2 : n // 2 + 30] = t[:30]
        t[-67:] = t[1:68]  # a match of 67 symbols, the last with nothing behind it
        for length in (64, 65, 66, 67):
            at = np.arange(n - length + 1)
            got = suffix.long_factors(t, at, length)
            assert [x.tolist() for x in got] == [(x[at] >= length).tolist() for x in suffix.longest_factors(t, length)]
            assert n < 140 or got[0].any()
            some = at[::3]
            same = [{int(j) for j in some if bytes(t[j : j + length]) == bytes(t[i : i + length])} for i in some]
            before, after = suffix.long_factors(t, some, length)
            assert before.tolist() == [min(x) < i for i, x in zip(some, same, strict=True)] and after.tolist() == [max(x) > i for i, x in zip(some, same, strict=True)]


def test_sieve_lets_every_key_through(spark):
    keys = spark.range(0, 4000, 2).select("id", F.lit("x").alias("s"))
    for of, rows in ((keys, 2000), (keys.limit(0), 0)):
        marked = common.sieve(of, rows, "id", "s")(spark.range(4000).select("id", F.lit("x").alias("s"))).collect()
        may = {r["id"] for r in marked if r["may"]}
        assert len(marked) == 4000 and set(range(0, 4000, 2)) & may == (set(range(0, 4000, 2)) if rows else set())
        assert sum(i % 2 for i in may) < 300 if rows else not may


def test_texts_without_repeats_are_not_dealt_out(spark):
    """Of 400 documents two have a passage in common: only their texts go through an exchange."""
    r = np.random.default_rng(5)
    texts = ["".join(map(chr, r.integers(97, 123, 600))) for _ in range(400)]
    texts[7] = texts[300][:300] + texts[7][:300]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    out = suffix.dedup(common.cut(docs), 200)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    got = {x["doc_id"]: x["n_bytes"] - len(x["kept"]) for x in out.collect()}
    assert len(got) == 400 and {k for k, n in got.items() if n} == {7, 300} and got[7] == got[300] == 300
    joined = plan[plan.index("Union") :]
    assert "Join LeftOuter" in joined and joined.count("getbit") >= 2


def test_contexts_beyond_a_broadcast(spark, monkeypatch):
    """Where shared anchors are too many to broadcast, results are the same."""
    monkeypatch.setattr(common, "BROADCAST_ROWS", 0)
    r = np.random.default_rng(6)
    texts = ["".join(map(chr, r.integers(97, 123, 500))) for _ in range(30)]
    texts[3] = texts[20][:250] + texts[3][:250] + texts[11][100:350]
    out = suffix.dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), 200)
    assert {x["doc_id"]: 0 if (n := x["n_bytes"] - len(x["kept"])) < 250 else n for x in out.collect() if x["n_bytes"] > len(x["kept"])} == {3: 500, 11: 250, 20: 250}


def test_ngrams_of_connected_classes_make_no_postings(spark, monkeypatch):
    """What only connected classes have in front is dropped before lists are made; what others share stays."""
    r = np.random.default_rng(7)
    words = [f"w{k}" for k in range(400)]
    rows = [(1, " ".join(words)), (2, " ".join(["x", *words[1:]])), (3, " ".join(r.permutation(words))), (4, " ".join(words)), (4, " ".join(words))]
    tables, cut = [], ngram_join.cut
    monkeypatch.setattr(ngram_join, "cut", lambda df, **sums: tables.append(cut(df, **sums)) or tables[-1])
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(x["doc_id"], x["component_id"]) for x in ngram_join.join(docs, 3, 90).collect()}
    assert got == {(1, 1), (2, 1), (3, 3), (4, 1)}
    shared = [common.told(t) for t in tables if t.columns == ["h"]]
    assert shared and max(shared) < 5
