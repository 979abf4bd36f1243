"""Operators on inputs beyond the sizes at which they once stopped doing the whole job."""

import numpy as np
import pyarrow as pa

from pyspark.sql import functions as F

from dagquotient.llm import bpe, ngram_join, shards, suffix, toxicity, urls


def _judged(spark, rows, bad):
    """url -> verdict and template, from urls with labels: 1 for those in ``bad``, 0 for those that it maps to 0."""
    pages = spark.createDataFrame(list(enumerate(rows)), "page_id long, url string")
    labels = spark.createDataFrame([(k, bad[u]) for k, u in enumerate(rows) if u in bad], "page_id long, label int")
    return {rows[r["page_id"]]: (r["verdict"], r["template"]) for r in urls.judge(pages, [], labels).collect()}


def test_url_branches_stay_apart_beside_many_rare_ones(spark):
    spam, news = ([f"http://h.org/{x}/{'a' * (k % 26 + 1)}{k}" for k in range(100)] for x in ("spam", "news"))
    slugs = [f"http://h.org/slug{chr(97 + k // 26)}{chr(97 + k % 26)}" for k in range(70)]
    got = _judged(spark, [*spam, *news, *slugs], {u: 1 for u in spam[:50]} | {u: 0 for u in news[:50]})
    assert {got[u] for u in spam} == {("block", "/spam/*")} and {got[u] for u in news} == {("allow", "/news/*")}
    assert {got[u] for u in slugs} == {("allow", "/*")}


def test_url_paths_are_followed_to_their_end(spark):
    deep = "http://h.org/a/b/c/d/e/f"
    spam, news = ([f"{deep}/{x}/{k}.html" for k in range(100)] for x in ("spam", "news"))
    giant = "http://h.org/a/b/c/d/e/g" + "/x" * 500
    got = _judged(spark, [*spam, *news, giant, deep], {u: 1 for u in spam[:30]} | {u: 0 for u in news[:90]})
    assert {got[u] for u in spam} == {("block", "/a/b/c/d/e/f/spam/*.html")}
    assert {got[u] for u in news} == {("allow", "/a/b/c/d/e/f/news/*.html")}
    assert got[deep] == ("allow", "/a/b/c/d/e/f") and got[giant] == ("allow", "/a/b/c/d/e/*" + "/x" * 500)


def test_bpe_goes_on_beyond_its_cache(monkeypatch):
    import public_tokenizers as P
    import tiktoken

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    ref, own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}), bpe.Codec(ranks, P.PATTERN)
    monkeypatch.setattr(bpe, "CACHE", 5)
    for lot in (["one two three", "four five six seven"], ["one"], ["two eight nine ten", "one two", ""], ["a b c d e f g h"], ["a b x y", "one"]):
        assert [np.frombuffer(x, "<u4").tolist() for x in own.encode_many(lot)] == [ref.encode_ordinary(t) for t in lot]


def test_suffix_windows_of_giant_texts_are_all_found(monkeypatch):
    monkeypatch.setattr(suffix, "GIANT", 4000)
    monkeypatch.setattr(suffix, "PIECE", 2000)
    monkeypatch.setattr(suffix, "BLOCK", 1)  # every text is alone in its lot
    r = np.random.default_rng(8)
    texts = [r.integers(97, 123, n).astype(np.uint8).tobytes() for n in (300, 1999, 2001, 3999, 4000, 4199, 6100, 9000)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array([0] * len(texts)), pa.array(texts, pa.binary())], ["d", "th", "raw"])
    found = {}
    for length in (64, 200):
        found.clear()
        for out in suffix._find(length)(iter([batch])):
            for x in out.to_pylist():
                found.setdefault(x["d"], []).extend(range(x["s"], x["s"] + x["n"]))
        assert {d: sorted(s) for d, s in found.items()} == {d: list(range(len(t) - length + 1)) for d, t in enumerate(texts)}


def test_near_copies_are_told_by_row_where_ids_repeat(spark):
    one, two, three = (" ".join(f"{w}{k}" for k in range(40)) for w in ("red", "blue", "green"))
    rows = [(5, one), (5, two), (5, two), (3, three), (5, three + " end"), (6, one + " end"), (7, two), (8, ""), (8, "  "), (9, one + " a"), (5, one + " b")]
    got = [(r["doc_id"], r["text"]) for r in ngram_join.dedup(spark.createDataFrame(rows, "doc_id long, text string"), 5, 80).collect()]
    ones = [x for x in got if x[1].startswith("red")]
    assert len(ones) == 1 and ones[0] in [(5, one), (5, one + " b")]
    assert sorted(x for x in got if x not in ones) == sorted([(5, two), (3, three), (8, ""), (8, "  ")])


def test_toxicity_swaps_every_sentence_of_a_text(spark, monkeypatch):
    words = "river stone cloud green paper walk seven light table garden".split()
    long_ = ". ".join(f"{words[k % 10]} {words[k // 10]} women" for k in range(80))
    rows = [(k, "plain text" if k % 4 else "you horrible scumbag", int(k % 4 == 0)) for k in range(400)] + [(k, long_, 1) for k in range(400, 420)]
    docs = spark.createDataFrame([x[:2] for x in rows], "doc_id long, text string")
    seen = []
    descend = toxicity._descend
    monkeypatch.setattr(toxicity, "_descend", lambda *a, **k: seen.append(a) or descend(*a, **k))
    model = toxicity.train(docs, spark.createDataFrame([(x[0], x[2]) for x in rows], "doc_id long, toxic int"), F.lit(True))

    def numbers(t):
        return frozenset(model.index[f] for f in toxicity.features(t) if f in model.index)

    want = {(numbers(a), numbers(b)) for a, b in [*toxicity._BARE, *toxicity.swapped(long_)]}
    few = {(numbers(a), numbers(b)) for a, b in [*toxicity._BARE, *toxicity.swapped(long_)[:100]]}
    pairs, times = seen[0][2], seen[0][3]
    assert len(want) > len(few) and times.sum() == len(want)
    assert {(frozenset(a.tolist()), frozenset(b.tolist())) for a, b in pairs} == {(a - b, b - a) for a, b in want}


def test_written_shards_keep_overflow_pages_apart(spark, tmp_path):
    rows = [(k, "x" * 50, "s") for k in range(30)] + [(7, "same " * 40, "s")] * 50 + [(8, "y" * 3000, "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, h string")
    shards.write(docs, 1000, str(tmp_path / "out"))
    out = spark.read.parquet(str(tmp_path / "out"))
    assert sorted(tuple(r) for r in out.select("doc_id", "text", "h").collect()) == sorted(rows)
    assert all(r["b"] <= 1000 or r["n"] == 1 for r in out.groupBy("shard").agg(F.sum(F.octet_length("text")).alias("b"), F.count("*").alias("n")).collect())
