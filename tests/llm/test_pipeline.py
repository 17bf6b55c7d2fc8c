"""The pipeline on the smallest tables against brute force, stage by stage."""

import hashlib

import corpus_pipeline
import numpy as np

from .test_operators import brute_dedup, docs_of


def near_kept(rows):
    """Smallest id of each component of texts with a five-word Jaccard similarity of 0.8 or more."""
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    root, having = {i: i for i in sets}, {}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, s in sets.items():
        for g in s or {()}:
            having.setdefault(g, []).append(i)
    for i, j in {(i, j) for ids in having.values() for i in ids for j in ids if i < j}:
        both = len(sets[i] & sets[j])
        if sets[i] == sets[j] or both * 5 >= len(sets[i] | sets[j]) * 4:
            a, b = sorted((top(i), top(j)))
            root[b] = a
    return {top(i) for i in sets}


def test_pipeline(spark, sf):
    documents = spark.read.parquet(f"{sf}/documents.parquet")
    columns, stages = documents.columns, dict(corpus_pipeline.STAGES)
    clean = stages["toxicity"](spark, documents, sf).persist()
    assert clean.columns == columns and 0.8 * documents.count() < clean.count() < documents.count()
    unique = stages["exact_dedup"](spark, clean, sf).persist()
    rows = [(r["doc_id"], r["text"]) for r in clean.collect()]
    want, n = brute_dedup(rows)
    assert unique.count() == n and {r["doc_id"] for r in unique.collect()} == {keep for _, keep, _, _ in want}
    single = stages["simhash"](spark, unique, sf).persist()
    assert {r["doc_id"] for r in single.collect()} == near_kept([(r["doc_id"], r["text"]) for r in unique.collect()])
    mixed = stages["mixing"](spark, single, sf).persist()
    assert mixed.columns == columns
    sizes = {r["doc_id"]: len(r["text"].split()) for r in single.collect()}
    total = sum(sizes.values())
    assert abs(sum(sizes[r["doc_id"]] for r in mixed.collect()) - total) < 0.05 * total
    out = stages["bpe"](spark, mixed, sf).collect()
    texts = {r["doc_id"]: r["text"] for r in mixed.collect()}
    assert len(out) == mixed.count()
    for r in out:
        assert r["decoded_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest()
        assert len(np.frombuffer(r["ids"], "<u4")) == r["n_tokens"]


def test_run_applies_all_stages(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert {"doc_id", "n_tokens", "ids"} <= set(out.columns) and out.count() > 0


def test_stages_on_odd_tables(spark, sf):
    """Nulls in every column, empty and long texts, repeated rows, clashing names, no rows at all."""
    rows = [(None, None, None, None), (1, "", "en", None), (2, "a b c d e f", None, "s"), (2, "a b c d e f", None, "s"), (None, "x y", "en", "s"), (3, "long words " * 20_000, "en", "t"), (4, " \t", "en", "t")]
    for table in (docs_of(spark, rows), docs_of(spark, rows[:0])):
        docs = table
        for name, stage in corpus_pipeline.STAGES:
            out = corpus_pipeline.materialise(stage(spark, docs, sf), f"test-{name}")
            if name != "bpe":
                assert out.columns == docs.columns
            n = {"toxicity": docs.count(), "exact_dedup": min(4, docs.count())}.get(name, out.count())
            assert out.count() == n, name
            docs = out
