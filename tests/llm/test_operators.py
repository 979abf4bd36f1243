"""Every operator against a brute-force version, on a small fixture with nulls, empty and long texts, ties and repeats."""

import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from dagquotient.llm import bpe, components, decontaminate, lines, ngram_join, quality, queries, shards, spotsigs, suffix, toxicity, urls

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, h long, s string, site string, pos int"


@pytest.fixture(scope="module")
def rows(spark):
    found = [(r["doc_id"], r["text"], r["source"]) for r in spark.read.parquet(f"{SF}/documents.parquet").orderBy("doc_id").limit(80).collect()]
    base = "Alpha the beta gamma of delta epsilon and zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau"
    odd = [(9001, None, None), (9002, "", "x"), (9003, "one", "y"), (9004, "one two", "y"), (9005, base, "a"), (9006, base, "b"), (9007, base + " upsilon", "c"), (9008, "é" * 700, "a"), (9009, "ab " * 900, None), (9010, "\n\n  \n", "a"), (None, base, "d")]
    return found + odd


@pytest.fixture(scope="module")
def docs(spark, rows):
    """With columns that have the names of inner ones, and one repeated row."""
    full = [(i, t, "en", s, None, 1, "s", "site", 3) for i, t, s in [*rows, rows[0]]]
    return spark.createDataFrame(full, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def one_each(df, rows):
    """Results by (id, text): a row for each row, equal for repeated ones."""
    got = df.collect()
    assert len(got) == len(rows) + 1
    return {r["doc_id"]: r for r in got}


def test_bpe_is_what_tiktoken_does(docs, none, rows):
    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_multi_50k.tiktoken")
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    got = one_each(bpe.round_trip(docs, path, P.PATTERN, keep_ids=True), rows)
    for i, text, _ in rows:
        want = ref.encode_ordinary(text or "")
        assert got[i]["ids"] == want and got[i]["n_tokens"] == len(want)
        assert got[i]["ids_sha256"] == hashlib.sha256(np.array(want, "<u4").tobytes()).hexdigest()
        assert got[i]["decoded_sha256"] == hashlib.sha256((text or "").encode()).hexdigest()
    coded = bpe.encode(docs, path, P.PATTERN)
    assert {r["doc_id"]: bytes(r["bytes"]) for r in bpe.decode(coded, path, P.PATTERN).collect()} == {i: (t or "").encode() for i, t, _ in rows}
    assert bpe.round_trip(none, path, P.PATTERN).count() == 0


def test_bpe_on_odd_characters():
    import public_tokenizers as P
    import tiktoken

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    ref, own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}), bpe.Codec(ranks, P.PATTERN)
    r = np.random.default_rng(5)
    for _ in range(200):
        text = "".join(chr(c) for c in r.choice([*range(9, 127), *range(0xA0, 0x500), *range(0x4E00, 0x4E80), 0x1F600, 0x2028, 0x3000], 60))
        assert own.encode(text).tolist() == ref.encode_ordinary(text) and own.decode(own.encode(text)) == text.encode()


def test_quality_on_held_out_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    fold = F.crc32(F.col("doc_id").cast("string")) % 5
    scored = quality.score(docs.select("doc_id", "text"), quality.train(docs, labels, fold != 0)).where(fold == 0)
    both = scored.join(labels, "doc_id").collect()
    assert np.mean([(r["score"] >= 0.3) == bool(r["quality"]) for r in both]) > 0.95


def test_quality_without_labels_or_rows(spark, docs, none, rows):
    labels = spark.createDataFrame([(1, None, None)], "doc_id long, quality int, toxic int")
    assert quality.train(docs, labels, F.lit(True)) is None
    assert {r["score"] for r in one_each(quality.score(docs, None), rows).values()} == {0.5}
    assert quality.score(none, None).count() == 0 and toxicity.score(none, None).count() == 0
    assert toxicity.train(docs, labels, F.lit(True)) is None


def test_forest_walks_like_its_trees():
    r = np.random.default_rng(1)
    x = r.normal(size=(400, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 3] > 0.5)).astype(float)
    f = quality.fit(x, y, trees=20, depth=3)
    total = np.full(len(x), f.base)
    for t in range(20):
        for i in range(len(x)):
            node = 0
            while node < 7:
                node = 2 * node + 1 + int(x[i, f.feature[t, node]] > f.threshold[t, node])
            total[i] += f.leaf[t, node - 7]
    assert np.allclose(f.score(x), 1 / (1 + np.exp(-total)))
    assert ((f.score(x) > 0.5) == y).mean() > 0.9


def test_toxicity_and_groups(spark):
    r = np.random.default_rng(2)
    words = "river stone cloud green paper walk seven light table garden".split()
    rows = []
    for i in range(600):
        bad = i % 4 == 0
        text = " ".join(r.choice(words, 12))
        name = str(r.choice(["women", "men"], p=[0.95, 0.05] if bad else [0.1, 0.9]))
        rows.append((i, f"{text} {name}" + (" you horrible scumbag" if bad else ""), int(bad)))
    docs = spark.createDataFrame([x[:2] for x in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(x[0], x[2]) for x in rows], "doc_id long, toxic int")
    model = toxicity.train(docs, labels, F.lit(True))
    assert abs(model.logit("we met women") - model.logit("we met men")) < 0.5
    p = model.score(["the women walk", "a horrible scumbag", None, ""])
    assert p[0] < 0.3 and p[1] > 0.7 and p[2] == p[3] < 0.3


def test_suffix_dedup(docs, none, rows):
    every = [*rows, rows[0]]
    for crowd in (3000, 1):
        suffix.CROWD = crowd
        for first in ("goes", "stays"):
            seen = {}
            for k, (_, t, _) in enumerate(every):
                b = (t or "").encode()
                for s in range(len(b) - 199):
                    seen.setdefault(b[s : s + 200], []).append((k, s))
            got = one_each(suffix.dedup(docs, 200, first), rows)
            # with first="stays" order is by id: rows here are in that order but for the null id and the repeated row
            for k, (i, t, _) in enumerate(rows):
                if first == "stays" and (i is None or i == rows[0][0] or t == rows[-1][1]):
                    continue
                b = (t or "").encode()
                gone = np.zeros(len(b), bool)
                for s in range(len(b) - 199):
                    at = seen[b[s : s + 200]]
                    if len(at) > 1 and (first == "goes" or at[0] != (k, s)):
                        gone[s : s + 200] = True
                assert bytes(got[i]["kept"]) == bytes(np.frombuffer(b, np.uint8)[~gone]) and got[i]["n_bytes"] == len(b)
    suffix.CROWD = 3000
    assert suffix.dedup(none).count() == 0


def test_longest_factors():
    r = np.random.default_rng(3)
    for n in (1, 2, 17, 60):
        t = r.integers(0, 2, n)
        before, after = suffix.longest_factors(t, 16)
        for i in range(n):
            for got, others in ((before, range(i)), (after, range(i + 1, n))):
                best = 0
                for j in others:
                    k = 0
                    while max(i, j) + k < n and t[i + k] == t[j + k]:
                        k += 1
                    best = max(best, k)
                assert min(best, 16) == got[i]


def _words5(t):
    t = (t or "").translate({c: c + 32 for c in range(65, 91)})
    return [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", t) if w]


def test_decontamination(spark, docs, none, rows):
    items = [(1, "gamma of delta epsilon and zeta eta theta iota kappa lambda mu"), (2, "ONE two"), (3, None), (4, "  "), (5, rows[3][1][40:300]), (5, "xi omicron pi rho"), (6, "not there at all")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = one_each(decontaminate.report(docs, bench, 10), rows)
    for i, t, _ in rows:
        w, hit, which = _words5(t), set(), set()
        for k, x in items:
            v = _words5(x)
            n = min(10, len(v))
            for s in range(len(v) - n + 1 if n else 0):
                for p in range(len(w) - n + 1):
                    if w[p : p + n] == v[s : s + n]:
                        hit.update(range(p, p + n))
                        which.add(str(k))
        assert (got[i]["n_words"], got[i]["n_hit"], got[i]["items"], got[i]["contaminated"]) == (len(w), len(hit), sorted(which), bool(hit)), i
    assert decontaminate.report(none, bench).count() == 0
    assert not any(r["contaminated"] for r in decontaminate.report(docs, bench.limit(0)).collect())
    bad = {i for i in got if got[i]["contaminated"]}
    assert {r["doc_id"] for r in decontaminate.clean(docs, bench).collect()} == {i for i, _, _ in rows} - bad


def _sets(t, n):
    t = (t or "").translate({c: c + 32 for c in range(65, 91)})
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", t) if x]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()


def _components(rows, n, percent):
    sets = [_sets(t, n) for _, t, _ in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    least = {}
    for k, (i, _, _) in enumerate(rows):
        if i is not None:
            least[find(k)] = min(least.get(find(k), i), i)
    return {i: (len(sets[k]), least.get(find(k)) if sets[k] else i) for k, (i, _, _) in enumerate(rows)}


@pytest.mark.parametrize(("n", "percent", "short", "block"), [(3, 90, 16, 256), (5, 80, 1, 2)])
def test_ngram_join(docs, none, rows, n, percent, short, block):
    ngram_join.SHORT, ngram_join.BLOCK_ROWS = short, block
    got = one_each(ngram_join.join(docs, n, percent), rows)
    ngram_join.SHORT, ngram_join.BLOCK_ROWS = 16, 256
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == _components(rows, n, percent)
    if short == 16:
        assert ngram_join.join(none).count() == 0


def test_ngram_dedup_keeps_one_of_each(docs, rows):
    want = _components(rows, 5, 80)
    got = [r["doc_id"] for r in ngram_join.dedup(docs, 5, 80).collect()]
    assert sorted(x for x in got if x is not None) == sorted(i for i, (_, c) in want.items() if i is not None and i == c)


def test_components(spark):
    edges = [(k, k + 1) for k in range(20)] + [(50, 51), (60, 50), (-3, 60)]
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{k: 0 for k in range(21)}, **{k: -3 for k in (50, 51, 60, -3)}}


def test_lines(docs, none, rows):
    first, sites = {}, {}
    for i, t, s in rows:
        for x in (t or "").split("\n"):
            if x.strip(" "):
                sites.setdefault(x.strip(" "), set()).add(s)
                first[x.strip(" ")] = min(first.get(x.strip(" "), 2**63), 2**63 - 1 if i is None else i)
    for least in (2, 3):
        got = one_each(lines.dedup(docs, least), rows)
        for i, t, _ in rows:
            kept, seen = [], set()
            for x in (t or "").split("\n"):
                y = x.strip(" ")
                if len(sites.get(y, ())) < least or (first[y] == (2**63 - 1 if i is None else i) and y not in seen):
                    kept.append(x)
                seen.add(y)
            assert (got[i]["text"] or "") == "\n".join(kept), i
            assert got[i]["h"] == 1 and got[i]["pos"] == 3
    assert lines.dedup(none).count() == 0


def test_urls(spark):
    rules = [urls.rule(x) for x in queries.RULES]
    cases = {
        "http://a.com/x": ("a.com", "/x", "com/", "allow"),
        "HTTPS://WWW.Example.COM/en/1?q#f": ("www.example.com", "/en/1", "www.example.com/en/", "allow"),
        "https://b.example.com/en/1": ("b.example.com", "/en/1", "example.com/en/", "block"),
        "http://badexample.com/en/1": ("badexample.com", "/en/1", "com/", "allow"),
        "x://q.net/es/": ("q.net", "/es/", "net/es/", "block"),
        "http://q.net/de/5": ("q.net", "/de/5", None, "allow"),
        "http://a.com": ("a.com", "", None, "allow"),
        "no url": ("", "", None, "allow"),
        "": ("", "", None, "allow"),
        None: ("", "", None, "allow"),
    }
    pages = spark.createDataFrame([(k, u) for k, u in enumerate([*cases, None])], "page_id long, url string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.judge(pages, rules).collect()}
    assert got == dict(enumerate([*cases.values(), cases[None]]))
    assert urls.judge(pages.limit(0), rules).count() == 0


def test_url_templates_learn_from_labels(spark):
    rows = [(k, f"http://h.org/{'spam' if k % 2 else 'news'}/{k}.html") for k in range(200)]
    labels = spark.createDataFrame([(k, k % 2) for k in range(0, 100)], "page_id long, label int")
    got = {r["page_id"]: (r["verdict"], r["template"]) for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string"), [], labels).collect()}
    assert all(got[k] == (("block", "/spam/*.html") if k % 2 else ("allow", "/news/*.html")) for k in range(200))


@pytest.mark.parametrize("limit", [3000, 100_000, 10**9])
def test_shards(docs, none, rows, limit):
    got = shards.assign(docs.unionByName(docs.where("doc_id = 3")).unionByName(docs.where("doc_id = 3")), limit).collect()
    assert len(got) == len(rows) + 3
    held = {}
    for r in got:
        held.setdefault((r["shard"], r["shard_bytes"]), []).append((r["h"], r["bytes"]))
    for (name, total), docs_in in held.items():
        depth, prefix, _ = name.split("-")
        assert sum(b for _, b in docs_in) == total and (total <= limit or len(docs_in) == 1)
        assert all(h >> (shards.BITS - int(depth)) == int(prefix, 16) for h, _ in docs_in)
    if limit == 3000:
        assert shards.assign(none, limit).count() == 0


def test_fingerprints(docs, none, rows):
    anchors = set(spotsigs.ANCHORS)

    def sigs(t):
        w = [x for x in re.split(r"[\W_]+", t.lower()) if x]
        out = set()
        for i, x in enumerate(w):
            chain = [y for y in w[i + 1 : i + 1 + spotsigs.REACH] if y not in anchors][:2]
            if x in anchors and len(chain) == 2:
                out.add((x, *chain))
        return out or {("p", *p) for p in zip(w, w[1:], strict=False)} or {("t", t)}

    got = {}
    for r in spotsigs.edited(docs.dropDuplicates(["doc_id"])).collect():
        got[r["doc_id"]] = r
    order = sorted(rows, key=lambda r: -(2**63) if r[0] is None else r[0], reverse=True)
    for k, (i, t, _) in enumerate(order):
        t, n = t or "", order[(k + 1) % len(order)][1] or ""
        half = len(t) // 2
        new = t[: len(t) - half] + n[:half]
        a, b, c = sigs(t), sigs(new), sigs(n)
        r = got[i]
        assert (r["n_chars"], r["edited_sha256"], len(r["fingerprint"].split(","))) == (len(t), hashlib.sha256(new.encode()).hexdigest(), len(a))
        assert r["near_edited"] == pytest.approx(len(a & b) / len(a | b)) and r["near_next"] == pytest.approx(len(a & c) / len(a | c))
    assert spotsigs.edited(none).count() == 0
    member, pairs = spotsigs.near(docs)
    ids = {r["doc_id"]: r["class_id"] for r in member.collect()}
    assert ids[9006] == 9005 and all(r["a"] < r["b"] and r["likeness"] >= 0.8 for r in pairs.collect())


def test_folds_are_those_of_the_contract(spark):
    got = {r["doc_id"]: r["k"] for r in spark.range(50).select(F.col("id").alias("doc_id")).select("doc_id", queries._fold(5).alias("k")).collect()}
    assert got == {i: zlib.crc32(str(i).encode()) % 5 for i in range(50)}
