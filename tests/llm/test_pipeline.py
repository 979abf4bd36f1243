import corpus_pipeline as P
from dagquotient.llm import lines
from tests.llm.test_operators import SF, _components, _words5


def test_stages_do_what_they_say(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").cache()
    out = {}
    for name, stage in P.STAGES:
        before = docs
        docs = stage(spark, before, SF).cache()
        out[name] = (before.collect(), docs.collect())
        if name != "tokens":
            assert sorted(docs.columns) == sorted(P.COLUMNS)
    bad = {r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").where("quality = 0").collect()}
    kept = {r["doc_id"] for r in out["quality"][1]}
    given = {r["doc_id"] for r in out["quality"][0]}
    assert len(kept & bad) <= 0.2 * len(bad) and len(given - kept - bad) < 0.2 * len(given)

    before, after = out["line_dedup"]
    assert {r["doc_id"] for r in before} == {r["doc_id"] for r in after}
    sites = {}
    for r in before:
        for x in r["text"].split("\n"):
            sites.setdefault(x.strip(" "), set()).add(r["source"])
    wide = {x for x, s in sites.items() if x and len(s) >= P.MIN_SITES}
    assert sum(x.strip(" ") in wide for r in after for x in r["text"].split("\n")) == len(wide)

    before, after = out["near_duplicates"]
    want = _components([(r["doc_id"], r["text"], None) for r in before], 5, 80)
    assert {r["doc_id"] for r in after} == {i for i, (_, c) in want.items() if i == c}

    before, after = out["decontamination"]
    windows = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = _words5(r["text"])
        n = min(10, len(w))
        windows |= {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if n else set()
    clean = {r["doc_id"] for r in before if not any(tuple(w[k : k + n]) in windows for n in {len(x) for x in windows} for w in [_words5(r["text"])] for k in range(len(w) - n + 1))}
    assert {r["doc_id"] for r in after} == clean

    before, after = out["tokens"]
    assert {r["doc_id"] for r in before} == {r["doc_id"] for r in after} and all(r["n_tokens"] == len(r["ids"]) for r in after)
    assert lines.LG_K == 10
