"""Each operator against brute force, on small fixtures with nulls, empty and long texts, ties, repeated rows, clashing columns."""

import hashlib
import random
import re
import zlib
from collections import Counter

import corpus_pipeline
import numpy as np
import public_tokenizers as tokenizers
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from vertimine.llm import bm25, bpe, common, exact_dedup, language, licenses, mixing, queries, quotes, simhash, token_files, toxicity

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, `key` int, size int, _text string"
UP = str.maketrans(common.UPPER, common.LOWER)
LONG = " ".join(f"word{i % 997}" for i in range(30_000))
TEXTS = [None, "", " \t\n", "Hello  World", "HelloWorld", "hello world", "a b c", "a b c d", "A B C D", LONG, LONG + " end", "ü ß 日本 🙂 \x0b\x1c", "x" * 5000, "Under CC BY, all rights\nreserved.", "CC BY all rights all RIGHTS reserved cc-by"]


def docs_of(spark, rows):
    """rows: (doc_id, text, lang, source); further columns clash with names the operators use inside."""
    return spark.createDataFrame([(i, t, lang, s, None, 1, 2, "z") for i, t, lang, s in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def rows():
    out = [(n, t, "en" if n % 2 else None, None if n % 5 == 0 else f"s{n % 3}") for n, t in enumerate(TEXTS)]
    out += [(3, "Hello  World", "en", "s0"), (None, "HelloWorld", None, None), (None, None, None, None), (40, "Hello World", "en", "s1"), (41, "Hello World", "en", "s1")]
    return out


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# Exact duplicates


def brute_dedup(rows):
    groups = {}
    for n, (i, t, *_) in enumerate(rows):
        groups.setdefault(re.sub("[\x20\x09-\x0d]", "", t or ""), []).append((-len(t or ""), i is None, i or 0, i))
    out = []
    for text, members in groups.items():
        best = min(members, key=lambda m: m[:3])
        for m in members:
            out.append((m[3], best[3], len(members), hashlib.sha256(text.encode()).hexdigest()))
    return Counter(out), len(groups)


@pytest.mark.parametrize("bits,capacity", [(64, 50_000), (64, 2), (3, 2), (0, 1)])
def test_exact_dedup(spark, rows, bits, capacity):
    got = exact_dedup.classify(docs_of(spark, rows), key_bits=bits or 1, capacity=capacity).collect()
    want, n = brute_dedup(rows)
    assert Counter((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got) == want
    assert sum(r["kept"] for r in got) == n
    kept = exact_dedup.keep_first(docs_of(spark, rows), key_bits=bits or 1, capacity=capacity)
    assert kept.columns == docs_of(spark, rows).columns and kept.count() == n


def test_directory_doubles_only_where_needed():
    d = exact_dedup.Directory.grown({0: 5, 1: 1, 2: 1, 7: 1}, 3, 4)
    assert d.depth == 3 and sorted(d.depths) == [1, 2, 3, 3]
    assert len(set(d.slots[4:])) == 1
    assert exact_dedup.Directory.grown({}, 0, 4).depth == 0


def test_exact_dedup_large_copy_group(spark):
    rows = [(i, "same text here", "en", "s") for i in range(3000)] + [(i, f"own {i}", "en", "s") for i in range(3000, 3300)]
    got = exact_dedup.classify(docs_of(spark, rows)).where("group_size = 3000 and keep_id = 0").count()
    assert got == 3000


# BPE


@pytest.fixture(scope="module")
def pair():
    import tiktoken

    own = bpe.PrefixBPE.load(tokenizers.path("byte_bpe_50k.tiktoken"), tokenizers.PATTERN)
    return own, tiktoken.Encoding("own", pat_str=tokenizers.PATTERN, mergeable_ranks=own.ranks, special_tokens={})


def test_bpe_query_columns(spark, rows, pair):
    _, other = pair
    got = bpe.encode(docs_of(spark, rows), tokenizers.path("byte_bpe_50k.tiktoken"), tokenizers.PATTERN).collect()
    want = Counter()
    for i, t, *_ in rows:
        ids = np.array(other.encode_ordinary(t or ""), "<u4").tobytes()
        want[i, len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in got) == want


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60))
def test_bpe_any_text(pair, text):
    text = text.encode("utf-8", "ignore").decode()
    own, other = pair
    assert own.encode(text) == other.encode_ordinary(text)
    assert own.decode(own.encode(text)) == text.encode()


def test_bpe_append_and_edit(pair):
    own, other = pair
    r = random.Random(3)
    for _ in range(200):
        data = bytes(r.choice(b"abethings ") for _ in range(r.randint(1, 400)))
        table = bpe.PrefixTable(own, data)
        assert table.ids() == other._encode_single_piece(data)
        at = r.randint(0, len(data))
        to = r.randint(at, min(len(data), at + 9))
        new = data[:at] + b"xthe" + data[to:]
        assert table.replace(at, to, b"xthe").ids() == other._encode_single_piece(new)
        assert table.append(b"ing").ids() == other._encode_single_piece(new + b"ing")


# Toxicity


def test_toxicity_learns_and_rejects(spark):
    r = random.Random(1)
    plain = [f"w{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(1200):
        bad = i % 6 == 0
        words = r.choices(plain, k=40) + (["vilethings", "vileness"][: 1 + i % 2] if bad else [])
        rows.append((i, " ".join(r.sample(words, len(words))), "en", "s"))
        labels.append((i, None, int(bad)))
    rows += [(5000, None, None, None), (5001, "", None, None), (None, "w1 vileword", None, None), (5000, None, None, None)]
    labels += [(6000, 1, 1), (None, 1, 1), (7, 1, None)]
    docs, marks = docs_of(spark, rows), spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int")
    model = toxicity.train(docs, marks.where(~toxicity.held_out()))
    truth = {i: y for i, _, y in labels if y is not None}
    scored = toxicity.with_scores(docs, model, "text", [docs.doc_id, toxicity.held_out().alias("held_out")], "doc_id bigint, held_out boolean, score double").collect()
    assert len(scored) == len(rows) and all(0 <= x["score"] <= 1 for x in scored)
    held = [x for x in scored if x["held_out"] and x["doc_id"] < 1200]
    assert all(x["held_out"] == (zlib.crc32(str(x["doc_id"]).encode()) % 5 == 0) for x in scored if x["doc_id"] is not None)
    assert np.mean([(x["score"] >= 0.5) == truth[x["doc_id"]] for x in held]) > 0.97
    kept = toxicity.keep_clean(docs, model)
    assert kept.columns == docs.columns and kept.count() == sum(x["score"] < 0.5 for x in scored)
    assert toxicity.keep_clean(empty(spark), model).count() == 0


def test_toxicity_fit_and_score_against_plain_loops():
    """FTRL by dictionaries and one feature at a time: the same weights and scores."""
    r = np.random.default_rng(4)
    ftrl = toxicity.FTRL(bits=8, l1=0.3, epochs=3)
    rows = [np.unique(r.integers(0, 256, r.integers(1, 20))) for _ in range(60)]
    labels = [int(3 in x or 7 in x) for x in rows]
    z, n, z0, n0 = Counter(), Counter(), 0.0, 0.0

    def weight(i):
        return 0.0 if abs(z[i]) <= ftrl.l1 else -(z[i] - np.sign(z[i]) * ftrl.l1) / ((ftrl.beta + n[i] ** 0.5) / ftrl.alpha + ftrl.l2)

    def base():
        return -z0 / ((ftrl.beta + n0**0.5) / ftrl.alpha)

    for _ in range(ftrl.epochs):
        for x, y in zip(rows, labels):
            w = {i: weight(i) for i in x.tolist()}
            g = 1 / (1 + np.exp(-(sum(w.values()) + base()))) - y
            w0 = base()
            for i, wi in w.items():
                z[i] += g - ((n[i] + g * g) ** 0.5 - n[i] ** 0.5) / ftrl.alpha * wi
                n[i] += g * g
            z0 += g - ((n0 + g * g) ** 0.5 - n0**0.5) / ftrl.alpha * w0
            n0 += g * g
    at, w, intercept = ftrl.fit(rows, labels)
    assert {int(i): pytest.approx(float(x), abs=1e-4) for i, x in zip(at, w)} == {i: weight(i) for i in z if weight(i)} and intercept == pytest.approx(base())


def test_toxicity_bounds_rows_of_the_driver(spark, monkeypatch):
    """An id that repeats, with one text and with many: at most max_train rows are fitted."""
    rows = [(1, "same words", "en", "s")] * 300 + [(1, f"other words {i}", "en", "s") for i in range(300)] + [(n, f"plain {n}", "en", "s") for n in range(2, 60)]
    seen, fit = [], toxicity.FTRL.fit
    monkeypatch.setattr(toxicity.FTRL, "fit", lambda self, x, y: seen.append(len(x)) or fit(self, x, y))
    labels = spark.createDataFrame([(n, int(n % 7 == 1)) for n in range(60)], "doc_id bigint, toxic int")
    model = toxicity.train(docs_of(spark, rows), labels, max_train=10)
    assert seen == [10] and 0 <= model.score(["x"], model.dense())[0] <= 1


def test_toxicity_without_labels(spark, rows):
    docs = docs_of(spark, rows)
    model = toxicity.train(docs, spark.createDataFrame([], "doc_id bigint, toxic int"))
    assert toxicity.keep_clean(docs, model).count() == len(rows)


# Mixing


def brute_targets(sizes):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    weight = {s: 1 + n % 3 for n, s in enumerate(names)}
    total, capped = sum(sizes.values()), set()
    while True:
        free = [s for s in names if s not in capped]
        rest = total - sum(3 * sizes[s] for s in capped)
        lam = rest / sum(weight[s] for s in free) if free else 0
        over = [s for s in free if weight[s] * lam > 3 * sizes[s]]
        if not over:
            return {s: 3.0 * sizes[s] if s in capped else weight[s] * lam for s in names}
        capped |= set(over)


def test_mixing(spark):
    r = random.Random(5)
    rows = [(i, " ".join(["w"] * int(r.paretovariate(1.2) * 20)), "en", "big" if i % 3 == 0 else f"s{i % 11}") for i in range(3000)]
    rows += [(4000, None, None, None), (4001, "one two", None, None), (4001, "one two", None, None), (None, "x y z", None, "tiny"), (4002, "", None, "empty")]
    got = mixing.digest(docs_of(spark, rows)).collect()
    assert len(got) == len(rows)
    sizes = Counter()
    for _, t, _, s in rows:
        sizes[s] += len(re.findall("[^\x20\x09-\x0d]+", t or ""))
    want = brute_targets(dict(sizes))
    by = {(x["source_size"], round(x["target"], 3)) for x in got}
    assert by == {(sizes[s], round(want[s], 3)) for s in sizes}
    assert all(x["taken"] in [x["size"] * k for k in range(4)] for x in got)
    source = {i: s for i, _, _, s in rows}
    taken = Counter()
    for x in got:
        taken[source[x["doc_id"]]] += x["taken"]
    for s in want:
        assert abs(taken[s] - want[s]) <= 0.002 * want[s] + 2, s
    # The same draws however rows are dealt to tasks, in the query and in the operator that returns rows.
    for parts in (1, 8):
        again = mixing.digest(docs_of(spark, rows[::-1]).repartition(parts)).collect()
        assert Counter(map(tuple, got)) == Counter(map(tuple, again))
        mixed = mixing.mix(docs_of(spark, rows).repartition(parts))
        assert mixed.columns == docs_of(spark, rows[:1]).columns
        assert Counter(r["doc_id"] for r in mixed.collect()) == +Counter({i: sum(x["copies"] for x in got if x["doc_id"] == i) for i, *_ in rows})
    assert mixing.digest(empty(spark)).count() == 0


def test_mixing_rows_alike(spark, monkeypatch):
    """Many rows alike in id, text and source: their copies add up to their share, none has more than one copy more than another."""
    monkeypatch.setattr(mixing, "REPEAT", 7)
    rows = [(1, "a b c d", "en", "s0")] * 101 + [(n, "x y", "en", "s1") for n in range(100, 400)] + [(1, "a b c d", "en", "s1")] * 3 + [(None, "q", None, None)] * 50
    for parts in (1, 5):
        docs = docs_of(spark, rows).repartition(parts)
        got = mixing.digest(docs).collect()
        assert len(got) == len(rows)
        for i, source_size in ((1, 404), (None, 50)):
            mine = [x["copies"] for x in got if x["doc_id"] == i and x["source_size"] == source_size]
            target, size = next((x["target"], x["size"]) for x in got if x["doc_id"] == i and x["source_size"] == source_size)
            assert max(mine) - min(mine) <= 1 and abs(sum(mine) * size - target) <= size
        taken = Counter(r["doc_id"] for r in mixing.mix(docs).collect())
        assert taken == +Counter({i: sum(x["copies"] for x in got if x["doc_id"] == i) for i, *_ in rows})


def test_pivot_keeps_words_and_expectation():
    size, f = np.array([50.0, 30, 20, 20, 10, 5]), np.array([0.3, 0.5, 0.5, 0.9, 0.2, 0.7])
    total, runs = np.zeros(6), 20_000
    for seed in range(runs):
        out, left = mixing.pivot(size, f, np.random.default_rng(seed))
        assert abs((out * size).sum() - (f * size).sum()) < 1e-6
        assert all(x in (0, 1) for n, x in enumerate(out) if n != left)
        total += out
    assert np.abs(total / runs - f).max() < 0.02


# SimHash


def brute_fingerprint(text):
    words = re.findall("[^\x20\x09-\x0d]+", (text or "").translate(UP))
    if not words:
        return 0
    grams = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))


def brute_components(fps, distance=2):
    parent = {f: f for f in fps}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    todo = sorted(parent)
    for n, a in enumerate(todo):
        for b in todo[n + 1 :]:
            if (a ^ b).bit_count() <= distance:
                parent[max(root(a), root(b))] = min(root(a), root(b))
    return {f: root(f) for f in fps}


def check_components(got, pairs):
    """pairs: (doc_id, fingerprint) of all rows."""
    roots = brute_components({f for _, f in pairs})
    least = {}
    for i, f in pairs:
        if i is not None:
            least[roots[f]] = min(i, least.get(roots[f], i))
    assert Counter((r["doc_id"], int(r["fingerprint"], 16), r["component_id"]) for r in got) == Counter((i, f, least.get(roots[f])) for i, f in pairs)


def test_simhash(spark, rows):
    base = " ".join(f"t{i}" for i in range(400))
    near = [(100 + n, base + f" tail{n}", "en", "s") for n in range(30)]
    got = simhash.classify(docs_of(spark, rows + near)).collect()
    check_components(got, [(i, brute_fingerprint(t)) for i, t, *_ in rows + near])
    assert simhash.classify(empty(spark)).count() == 0


@pytest.mark.parametrize("task_rows", [1_000_000, 40])
def test_hamming_links_of_dense_clusters(spark, monkeypatch, task_rows):
    """Chains and balls of fingerprints, so that components need several rounds and groups are large; leading blocks cut into parts."""
    monkeypatch.setattr(simhash, "TASK_ROWS", task_rows)
    r = random.Random(9)
    fps = [r.getrandbits(64) for _ in range(300)]
    chain = r.getrandbits(64)
    for n in range(60):
        chain ^= 1 << r.randrange(64) | 1 << r.randrange(64)
        fps.append(chain)
    centre = r.getrandbits(64)
    fps += [centre ^ (1 << a) ^ (1 << b) for a in range(0, 64, 3) for b in range(0, 64, 5)]
    fps += [0, (1 << 64) - 1, 1, 1 << 63]
    frame = spark.createDataFrame([(n, f - (1 << 64) if f >> 63 else f) for n, f in enumerate(fps)], "doc_id bigint, fp bigint")
    got = simhash.grouped(common.materialise(frame, "t")).collect()
    roots = brute_components(set(fps))
    least = {}
    for n, f in enumerate(fps):
        least.setdefault(roots[f], n)
    assert {r["doc_id"]: r["component_id"] for r in got} == {n: least[roots[f]] for n, f in enumerate(fps)}


def test_gray_index_prunes_groups():
    """All links of one group of random and near fingerprints, with far fewer comparisons than pairs."""
    r = np.random.default_rng(3)
    base = r.integers(0, 1 << 63, 3000, np.uint64)
    fp = np.unique(np.concatenate([base, base[:300] ^ np.uint64(1 << 40 | 1), base[:50] ^ np.uint64(1 << 62)]))
    fp = fp[np.argsort(simhash.gray_rank(fp))]
    index = simhash.GrayIndex(np.zeros(len(fp), np.int64), fp)
    got = {(int(i), int(j)) for a, b in index.links(2) for i, j in zip(a, b)}
    assert got == {(i, j) for i in range(len(fp)) for j in (np.flatnonzero(np.bitwise_count(fp[i + 1 :] ^ fp[i]) <= 2) + i + 1).tolist()} and len(got) >= 350
    lead = np.array([~np.uint64(0) << np.uint64(43)])
    led = {(int(i), int(j)) for a, b in index.links(2, lead) for i, j in zip(a, b)}
    assert led == {(i, j) for i, j in got if (fp[i] ^ fp[j]) >> np.uint64(43) == 0} and index.compared < 40 * len(fp)


def test_near_copies_of_the_stage(spark, monkeypatch):
    """Near copies at a five-word Jaccard of 0.8, far more than two bits apart, go; all links equal brute force, also over rounds of pivots."""
    monkeypatch.setattr(simhash, "FIRST_PIVOTS", 2)
    r = random.Random(8)
    line = " ".join(f"common{i}" for i in range(12))
    many = []
    for c in range(12):
        base = [f"w{r.randrange(3000)}" for _ in range(r.randint(5, 90))]
        for _ in range(r.choice([1, 2, 30])):
            words = list(base)
            for _ in range(r.randint(0, 3)):
                words[r.randrange(len(words))] = f"new{r.randrange(10**6)}"
            many.append(" ".join([*words, line] if c % 3 == 0 else words))
    texts = [None, "", "a b c", "A  b c", "a b c d", line, *many]
    docs = [(n, t, "en", "s") for n, t in enumerate(texts)]

    def grams(t):
        w = (t or "").lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets, root = [grams(t) for t in texts], list(range(len(texts)))
    n_far = 0
    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] == sets[j] or both * 5 >= len(sets[i] | sets[j]) * 4:
                n_far += (brute_fingerprint(texts[i]) ^ brute_fingerprint(texts[j])).bit_count() > 2
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if x == old else x for x in root]
    assert n_far > 10
    got = {x["doc_id"] for x in simhash.keep_one(docs_of(spark, docs)).collect()}
    assert got == set(root) and simhash.keep_one(empty(spark)).count() == 0


def test_candidates_of_the_simhash_stage_grow_with_its_texts(spark, monkeypatch):
    """Texts that share whole passages, and near copies: a pair that can't be alike is seldom proposed, and no pair once for each shingle it shares."""
    rng, made, rows = random.Random(5), simhash.pivot_pairs, []
    passages = [" ".join(f"p{p}w{w}" for w in range(60)) for p in range(12)]
    mixed = sorted({tuple(sorted(rng.sample(range(12), 6))) for _ in range(60)})
    copied = [f"c{n} " + " ".join(f"v{w}" for w in range(200)) + f" d{n}" for n in range(40)]
    texts = [" ".join(passages[p] for p in chosen) for chosen in mixed] + copied
    monkeypatch.setattr(simhash, "simhash_pairs", lambda sets, distance: sets.selectExpr("fp a", "fp b").limit(0))
    monkeypatch.setattr(simhash, "pivot_pairs", lambda *x: rows.append((found := made(*x)).count()) or found)
    kept = {r["doc_id"] for r in simhash.keep_one(docs_of(spark, [(n, t, "en", "s") for n, t in enumerate(texts)])).collect()}
    assert kept == {*range(len(mixed)), len(mixed)}
    assert sum(rows) < 1500, rows
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "simhash", "mixing", "bpe"]


def test_shuffle_paths_give_the_same(spark, rows, monkeypatch):
    """With nothing small enough to broadcast: salted joins and shuffled anti joins."""
    many = rows + [(200 + n, "Hello World", "en", "s1") for n in range(40)]
    monkeypatch.setattr(common, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(common, "SALT_ROWS", 4)
    want, n = brute_dedup(many)
    got = exact_dedup.classify(docs_of(spark, many)).collect()
    assert Counter((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got) == want
    check_components(simhash.classify(docs_of(spark, many)).collect(), [(i, brute_fingerprint(t)) for i, t, *_ in many])
    assert mixing.digest(docs_of(spark, many)).count() == len(many)


# Licenses


def test_licenses(spark, rows):
    mit = "Permission is hereby granted, free of charge, to any person obtaining a copy of this nice software and associated documentation files."
    more = rows + [(60, "x " + mit, None, None), (61, "the general public license general public license", None, None), (62, "permission is granted", None, None)]
    rows_, spans = licenses.scan(docs_of(spark, more))
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    want = Counter()
    for i, t, *_ in more:
        w = word.findall((t or "").translate(UP))
        for phrase, label in licenses.PHRASES.items():
            p = phrase.split()
            for at in range(len(w) - len(p) + 1):
                if w[at : at + len(p)] == p:
                    want[i, label, at] += 1
    joined = rows_.join(spans, "_row").where("exact")
    assert Counter((r["doc_id"], r["label"], r["first"]) for r in joined.collect()) == want
    assert Counter((r["doc_id"], r["n_words"]) for r in rows_.collect()) == Counter((i, len(word.findall((t or "").translate(UP)))) for i, t, *_ in more)
    long = rows_.join(spans, "_row").where("not exact").collect()
    assert [(r["doc_id"], r["label"]) for r in long] == [(60, "mit")] and 0.6 <= long[0]["cover"] <= 1


def brute_cover(words, template, k):
    """Template words in grams that stand on diagonals which follow each other by SHIFT at most: the best span's share."""
    hits = [(x - t, t) for t in range(len(template) - k + 1) for x in range(len(words) - k + 1) if words[x : x + k] == template[t : t + k]]
    best, span, before = 0.0, set(), None
    for d, t in sorted(hits):
        if before is not None and d - before > licenses.SHIFT:
            span = set()
        span |= set(range(t, t + k))
        before, best = d, max(best, len(span) / len(template))
    return best


def test_license_query_against_brute_force(spark, tmp_path):
    """All columns of the query, on texts with templates whole, changed, repeated, cut off, and one gram of them a hundred times."""
    r = random.Random(2)
    texts = [None, "", "cc by", "CC-BY 4.0 general public license, all rights reserved; cc by"]
    for name in list(licenses.TEXTS)[:4]:
        w = name.split()
        texts += [name.upper(), "pre " + name + " post " + name, " ".join(w[: len(w) // 2]), " ".join(w[:4]) + " x " * 3, (" ".join(w[:4]) + " ") * 100]
        for _ in range(6):
            changed = list(w)
            for _ in range(r.randint(1, 5)):
                at = r.randrange(len(changed))
                changed[at : at + r.randint(0, 1)] = [f"new{r.randrange(9)}"] * r.randint(0, 2)
            texts.append("Some words. " + " ".join(changed) + " cc by")
    docs = spark.createDataFrame([(n, t) for n, t in enumerate(texts)], "doc_id bigint, text string")
    docs.write.parquet(f"file://{tmp_path}/documents.parquet")
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    got = {x["doc_id"]: x for x in queries.QUERIES["op2_license_diagonals"](spark, f"file://{tmp_path}").collect()}
    assert len(got) == len(texts)
    for n, t in enumerate(texts):
        w = word.findall((t or "").translate(UP))
        base = [(at, label) for p, label in licenses.PHRASES.items() for at in range(len(w)) if w[at : at + len(p.split())] == p.split()]
        covers = {p: brute_cover(w, p.split(), licenses.LONG_K) for p in licenses.TEXTS}
        own = {licenses.TEXTS[p] for p, c in covers.items() if c >= licenses.MIN_COVER}
        places = [at for at, _ in base]
        x = got[n]
        assert (x["n_words"], x["n_base"], x["first_word"], x["last_word"]) == (len(w), len(base), min(places, default=None), max(places, default=None))
        assert x["base_labels"] == ",".join(sorted({b for _, b in base})) and x["labels"] == ",".join(sorted({b for _, b in base} | own)), t
        assert x["score"] == pytest.approx(max([1.0] * bool(base) + [c for c in covers.values() if c >= licenses.MIN_COVER], default=0.0))


# Search


def brute_bm25(rows, query, k):
    n = len(rows)
    counted = [(i, Counter(bm25.words(t))) for i, t, *_ in rows]
    mean = sum(sum(c.values()) for _, c in counted) / n
    df = Counter(w for _, c in counted for w in c)
    out = []
    for i, c in counted:
        size = sum(c.values())
        s = sum(q * np.log1p((n - df[w] + 0.5) / (df[w] + 0.5)) * c[w] * 2.2 / (c[w] + 1.2 * (0.25 + 0.75 * size / mean)) for w, q in Counter(bm25.words(query)).items() if w in c)
        if s > 0:
            out.append((-round(float(s), 9), i is None, i or 0, i))
    return [(x[3], -x[0]) for x in sorted(out, key=lambda x: x[:3])[:k]]


def test_bm25(spark, rows, monkeypatch):
    monkeypatch.setattr(bm25, "SHARD_DOCS", 97)
    r = random.Random(4)
    words = [f"v{int(r.paretovariate(0.7))}" for _ in range(5000)]
    many = rows + [(100 + n, " ".join(r.choices(words, k=r.randint(1, 60))), "en", "s") for n in range(700)]
    queries = [(1, "v1 v2 v3"), (2, "v1 v1 v977 hello WORLD"), (3, None), (4, "absent"), (5, " ".join(words[:40])), (6, "cc by")]
    got = bm25.BM25Index.build(docs_of(spark, many)).search(queries, 7)
    found = {}
    for x in got.orderBy("query_id", "place").collect():
        found.setdefault(x["query_id"], []).append((x["doc_id"], x["score"]))
    for i, text in queries:
        want = brute_bm25(many, text or "", 7)
        assert [s for _, s in found.get(i, [])] == pytest.approx([s for _, s in want], abs=1e-6), i
        assert {d for d, s in found.get(i, []) if s > want[-1][1] + 1e-6} == {d for d, s in want if s > want[-1][1] + 1e-6}
    assert bm25.BM25Index.build(empty(spark)).search(queries, 3).count() == 0


def test_bm25_queries_are_documents(spark, sf, monkeypatch):
    """Every document with an id divisible by 20 is a query, whole, over several passes; scores as by brute force."""
    monkeypatch.setattr(bm25, "PASS_QUERIES", 4)
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    found = {}
    for x in queries.QUERIES["op4_bm25_documents"](spark, sf).orderBy("query_id", "place").collect():
        found.setdefault(x["query_id"], []).append(x["score"])
    asked = [(i, t) for i, t in docs if i % 20 == 0]
    assert len(asked) == 10 and set(found) <= {i for i, _ in asked}
    for i, text in asked:
        assert found.get(i, []) == pytest.approx([s for _, s in brute_bm25(docs, text or "", 10)], abs=2e-5), i


@pytest.mark.parametrize("common, most", [(16, 1024), (2, 3), (10**6, 1024)])
def test_queries_together(spark, rows, monkeypatch, common, most):
    """Many queries through a shard at once: as brute force, whichever terms are in the matrix; ties by id, null and repeated ids, hits of one shard only."""
    for name, x in {"SHARD_DOCS": 150, "TOGETHER": 1, "GROUP": 5, "GROUP_POSTINGS": 4000, "COMMON": common, "MATRIX_ROWS": most}.items():
        monkeypatch.setattr(bm25, name, x)
    r = random.Random(6)
    words = [f"v{int(r.paretovariate(0.7))}" for _ in range(5000)]
    many = rows + [(100 + n, " ".join(r.choices(words, k=r.randint(1, 60))), "en", "s") for n in range(700)] + [(1000 + n, "same text v1 v2 v5", "en", "s") for n in range(30)]
    asked = [(n, t) for n, (_, t, *_) in enumerate(many) if n % 15 == 0] + [(9001, None), (9002, "absent"), (9003, "same text"), (9004, " ".join(words[:400])), (9005, "v1 v1 v2")]
    found = {}
    for x in bm25.BM25Index.build(docs_of(spark, many)).search(asked, 7).orderBy("query_id", "place").collect():
        found.setdefault(x["query_id"], []).append((x["doc_id"], x["score"]))
    for i, text in asked:
        want = brute_bm25(many, text or "", 7)
        assert [s for _, s in found.get(i, [])] == pytest.approx([s for _, s in want], abs=1e-8), i
        assert [d for d, _ in found.get(i, [])] == [d for d, _ in want], i
    assert bm25.BM25Index.build(empty(spark)).search(asked, 3).count() == 0


def test_queries_together_skip_ranges():
    """Ranges that a query's bounds rule out aren't scored, and few documents are scored exactly; the best are those of full scores."""
    import pyarrow as pa

    r, number, found, lengths = np.random.default_rng(3), {}, [], []
    for d in range(4000):  # four languages one after another, with some words of all
        w = [b"%d" % x for x in np.minimum(r.zipf(1.3, 80), 5000) + d // 1000 * 5000] + [b"all%d" % x for x in r.integers(0, 30, 20)]
        t, n = np.unique([number.setdefault(x, len(number)) for x in w], return_counts=True)
        found.append((t, n))
        lengths.append(len(w))
    columns = ["bucket", "terms", "dfs", "blocks", "docs", "tfs", "block_no", "block_tf", "block_len", "block_n", "ids", "lengths"]
    made = dict(zip(columns, zip(*bm25._shard(list(range(4000)), number, found, lengths))))
    shard = pa.table({c: pa.array([b"" if c in ("docs", "tfs", "block_no", "block_tf", "block_len", "block_n") and x == [] else x for x in made[c]]) for c in columns})
    together = bm25.Together(shard, pa.array([w.decode() for w in number]), 100.0)
    asked, weights = range(0, 4000, 20), r.random(len(number))
    starts = np.cumsum([0, *(len(found[d][0]) for d in asked)])
    term = np.concatenate([found[d][0] for d in asked])
    got = {j: (docs, scores) for j, docs, scores, _ in together.best(starts, term, weights[term], 10)}
    for j, d in enumerate(asked):
        mine = set(found[d][0].tolist())
        full = [sum(weights[t] * n * 2.2 / (n + 1.2) for t, n in zip(a.tolist(), b.tolist()) if t in mine) for a, b in found]
        want = sorted((-round(float(s), 9), i) for i, s in enumerate(full) if s > 0)[:10]
        assert got[j][0] == [i for _, i in want] and got[j][1] == pytest.approx([-s for s, _ in want], abs=1e-8)
    assert together.skipped > together.scored and together.exact < 15 * len(asked)


def test_queries_together_in_rounds(spark, rows, monkeypatch):
    """Rounds of 1, 1, 2, 4, ... shards, with each query's k-th best score so far: as brute force, ties over several shards by id, and few rows a round."""
    for name, x in {"SHARD_DOCS": 40, "TOGETHER": 1, "GROUP": 5, "ROUND": 1, "ROUND_GROWTH": 2}.items():
        monkeypatch.setattr(bm25, name, x)
    r = random.Random(8)
    words = [f"v{int(r.paretovariate(0.7))}" for _ in range(5000)]
    many = rows + [(100 + n, " ".join(r.choices(words, k=r.randint(1, 60))), "en", "s") for n in range(500)] + [(2000 - n, "same text v1 v2 v5", "en", "s") for n in range(60)]
    r.shuffle(many)
    asked = [(n, t) for n, (_, t, *_) in enumerate(many) if n % 15 == 0] + [(9001, None), (9002, "absent"), (9003, "same text"), (9004, " ".join(words[:400])), (9005, "v1 v1 v2")]
    index, found, sizes = bm25.BM25Index.build(docs_of(spark, many)), {}, []
    top = bm25.BM25Index._top
    monkeypatch.setattr(bm25.BM25Index, "_top", staticmethod(lambda best, k: sizes.append(best.count()) or top(best, k)))
    for x in index.search(asked, 7).orderBy("query_id", "place").collect():
        found.setdefault(x["query_id"], []).append((x["doc_id"], x["score"]))
    for i, text in asked:
        want = brute_bm25(many, text or "", 7)
        assert [s for _, s in found.get(i, [])] == pytest.approx([s for _, s in want], abs=1e-8), i
        assert [d for d, _ in found.get(i, [])] == [d for d, _ in want], i
    # Rows of each round, the best so far among them; without the scores of earlier rounds the last has half the shards' k best of each query.
    shards = index.rows.where("bucket = -1").count()
    assert len(sizes) >= 4 and sizes[-1] < 7 * len(asked) * (1 + shards / 4)


def test_queries_together_memory():
    """What a shard's search holds beside its rows stays within 50 bytes a posting, however many postings a group of queries has; scores in other shards leave out what is below."""
    import tracemalloc

    import pyarrow as pa

    r, number, found = np.random.default_rng(5), {}, []
    for _ in range(3000):
        t, n = np.unique([number.setdefault(b"%d" % x, len(number)) for x in r.integers(0, 6000, 150)], return_counts=True)
        found.append((t, n))
    columns = ["bucket", "terms", "dfs", "blocks", "docs", "tfs", "block_no", "block_tf", "block_len", "block_n", "ids", "lengths"]
    made = dict(zip(columns, zip(*bm25._shard(list(range(3000)), number, found, [150] * 3000))))
    shard = pa.table({c: pa.array([b"" if c in ("docs", "tfs", "block_no", "block_tf", "block_len", "block_n") and x == [] else x for x in made[c]]) for c in columns})
    names, asked = pa.array([w.decode() for w in number]), [d % 3000 for d in range(0, 3840, 10)]
    starts, term = np.cumsum([0, *(len(found[d][0]) for d in asked)]), np.concatenate([found[d][0] for d in asked])
    tracemalloc.start()
    together = bm25.Together(shard, names, 150.0)
    got = {j: scores for j, _, scores, _ in together.best(starts, term, np.ones(len(term)), 10)}
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 50 * sum(len(t) for t, _ in found)
    floors = np.array([got[j][2] for j in range(len(asked))])
    again = bm25.Together(shard, names, 150.0)
    assert {j: scores for j, _, scores, _ in again.best(starts, term, np.ones(len(term)), 10, floors)} == {j: [x for x in scores if x >= floors[j]] for j, scores in got.items()}
    assert again.exact < together.exact / 2


def test_wand_skips_and_equals_full_scores():
    """One shard against sums over all postings, ties included; with few rare terms most postings are never scored."""
    import pyarrow as pa

    r = np.random.default_rng(2)
    n = 4000
    ids = pa.array(range(n))
    lengths = r.integers(5, 90, n)
    for terms in (1, 3, 12, 40):
        rows, full = [], np.zeros(n)
        plan = [(t, float(np.round(r.random() * 3 + 0.1, 1))) for t in range(terms)]
        for t, w in plan:
            doc = np.unique(r.integers(0, n, r.integers(n // 4, n // 2)))
            tf = r.integers(1, 4, len(doc)) * np.where(r.random(len(doc)) < 0.01, 9, 1)
            impact = tf * (bm25.K1 + 1) / (tf + bm25.K1 * (1 - bm25.B + bm25.B * lengths[doc] / lengths.mean()))
            full[doc] += w * impact
            no, first, size = np.unique(doc // bm25.BLOCK, return_index=True, return_counts=True)
            rows.append((t, doc.astype("<u2").tobytes(), tf.astype("<u4").tobytes(), no.astype("<u2").tobytes(), np.maximum.reduceat(tf, first).astype("<u4").tobytes(), np.minimum.reduceat(lengths[doc], first).astype("<u4").tobytes(), size.astype(np.uint8).tobytes()))
        shard = bm25.Shard(pa.table(dict(zip(["term", "docs", "tfs", "block_no", "block_tf", "block_len", "block_n"], map(pa.array, zip(*rows))))), lengths, lengths.mean())
        got = shard.best(plan, 10, ids)
        full = np.round(full, 9)
        want = sorted(((-s, d) for d, s in enumerate(full) if s > 0))[:10]
        assert [d for d, _ in got] == [d for _, d in want] and [s for _, s in got] == pytest.approx([-s for s, _ in want])
        assert shard.scored + shard.passed + shard.skipped == sum(len(x[1]) // 2 for x in rows)
        if terms <= 3:
            assert shard.scored < 0.5 * (shard.scored + shard.passed + shard.skipped)


# Token files


def test_token_files(spark, rows, monkeypatch):
    monkeypatch.setattr(token_files, "BLOCK_ROWS", 4)
    from tokenizers import Tokenizer

    path = tokenizers.path("word_bpe_49k.json")
    more = [*rows, (70, "Say <|endoftext|> now, it's İstanbul ΑΣ ½ ﬁ", None, None)]
    files = token_files.write_corpus(docs_of(spark, more), path, 2)
    got = files.digests().collect()
    t = Tokenizer.from_file(path)
    want = Counter()
    for i, text, *_ in more:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        want[i, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in got) == want
    at = 0
    for r in sorted(got, key=lambda r: r["start"]):
        assert r["start"] == at
        at += r["n_tokens"]
    order = [r["doc_id"] if r["doc_id"] is not None else -1 for r in sorted(got, key=lambda r: r["start"])]
    assert order == sorted(order)
    assert token_files.write_corpus(empty(spark), path, 2).digests().count() == 0


def test_pieces_by_code_point():
    """Every character below U+0250, alone, within and beside words, in texts that are looked up word by word; other rules go to the library."""
    from tokenizers import Tokenizer

    path = tokenizers.path("word_bpe_49k.json")
    t, table = Tokenizer.from_file(path), token_files.PieceTokenizer(path)
    texts = ["a \x00 b", "a \x07 b", "a\x7fb !\x07", "\x01\x02", *[f"x {chr(c)} y{chr(c)}z !{chr(c)}" for c in range(0x250)], *[f"a{chr(c)}" for c in range(0x250)], *[f"{chr(c)}{chr(c)}a '{chr(c)}S" for c in range(0x250)]]
    assert table.by_words and not token_files.PieceTokenizer(tokenizers.path("byte_bpe_50k.json")).by_words
    for text, got in zip(texts, table.encode(texts), strict=True):
        assert np.frombuffer(got, "<u4").tolist() == t.encode(text, add_special_tokens=False).ids, ascii(text)


@settings(max_examples=300, deadline=None)
@given(st.text(st.characters(codec="utf-8"), max_size=40))
def test_pieces_of_any_text(text):
    from tokenizers import Tokenizer

    path = tokenizers.path("word_bpe_49k.json")
    if "t" not in _PIECES:
        _PIECES.update(t=Tokenizer.from_file(path), p=token_files.PieceTokenizer(path))
    assert np.frombuffer(_PIECES["p"].encode([text])[0], "<u4").tolist() == _PIECES["t"].encode(text, add_special_tokens=False).ids


_PIECES: dict = {}


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 2**32 - 1)))
def test_pack_round_trip(values):
    v = np.array(values, "<u4")
    assert (token_files.unpack(*token_files.pack(v), len(v)) == v).all()


# Language


def test_language(spark):
    r = random.Random(6)
    kinds = {"xx": ["tha", "ing", "oth", "er", "and"], "yy": ["que", "ción", "los", "ará", "ella"], "zz": ["sch", "ung", "keit", "über", "und"]}

    def prose(lang, n):
        return " ".join("".join(r.choices(kinds[lang], k=r.randint(1, 3))) for _ in range(n))

    rows = [(i, prose(lang, r.randint(3, 80)), lang, None) for i, lang in enumerate(r.choices(list(kinds), k=600))]
    docs = docs_of(spark, rows)
    model = language.train(docs.where(~language.held_out()))
    assert model[0] == ["xx", "yy", "zz"]
    odd = [(900, None, None, None), (901, "", None, None), (902, "123 !!", None, None), (903, prose("xx", 60) + " " + prose("zz", 60), None, None), (None, prose("yy", 30), None, None), (904, "日本", None, None)]
    got = {x["doc_id"]: x for x in language.predict(docs_of(spark, rows + odd), model, ["doc_id"], "doc_id bigint", shares=True).collect()}
    held = [i for i, *_ in rows if zlib.crc32(str(i).encode()) % 4 == 2]
    assert np.mean([got[i]["lang_pred"] == rows[i][2] for i in held]) > 0.97
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (900, 901, 902))
    assert set(got[903]["languages"]) == {"xx", "zz"} and abs(got[903]["languages"]["xx"] - 0.5) < 0.15
    assert got[904]["lang_pred"] in model[0] and got[None]["lang_pred"] == "yy"
    none = language.predict(docs_of(spark, rows[:3]), language.train(empty(spark)), ["doc_id"], "doc_id bigint").collect()
    assert all(x["lang_pred"] == "und" for x in none)


def test_mixture_against_plain_em():
    """EM and the choice of languages for one text after another, with loops."""
    r = np.random.default_rng(8)
    langs, n_units = 5, np.array([1, 3, 20, 40, 7])
    units = r.normal(-60, 4, (n_units.sum(), langs)).astype(np.float32)
    first = np.cumsum(n_units) - n_units
    units[first[2] : first[2] + 10, 0] += 30
    units[first[2] + 10 : first[2] + 20, 3] += 30
    share, _ = language.mixture(units, first, n_units)
    for i, (s, n) in enumerate(zip(first, n_units)):
        rows = units[s : s + n].astype(np.float64)

        def em(active):
            like = np.exp(rows - rows.max(1, keepdims=True))
            p = active / active.sum()
            for _ in range(language.ROUNDS):
                post = like * p
                post /= np.maximum(post.sum(1, keepdims=True), 1e-30)
                p = post.sum(0) / post.sum()
            return p, np.log(np.maximum((like * p).sum(1), 1e-30)).sum() + rows.max(1).sum()

        active = np.ones(langs)
        p, score = em(active)
        while active.sum() > 1:
            trial = active.copy()
            trial[np.where(active > 0, p, np.inf).argmin()] = 0
            p2, score2 = em(trial)
            if score - score2 > language.PENALTY * (1 + 0.5 * np.log1p(n)):
                break
            active, p, score = trial, p2, score2
        assert (share[i] > 0).tolist() == (p > 0).tolist() and share[i] == pytest.approx(p, abs=1e-3)


def test_many_languages(spark):
    """More labels than a fixed table would hold, and a text far longer than what is looked up at once."""
    assert language.bits_for(4) == 16 and language.bits_for(300) == 15 and language.bits_for(10**6) == 8
    rows = [(i, f"{chr(97 + i % 26)}{chr(97 + i // 26 % 26)} " * 30, f"l{i:03}", None) for i in range(300)] + [(1000, "ba " * 2_000_00, None, None)]
    model = language.train(docs_of(spark, rows))
    assert len(model[0]) == 300 and model[1].shape == (1 << 15, 300)
    got = {x["doc_id"]: x["lang_pred"] for x in language.predict(docs_of(spark, rows[:20] + rows[-1:]), model, ["doc_id"], "doc_id bigint").collect()}
    assert got[1000] == "l001" and sum(got[i] == f"l{i:03}" for i in range(20)) >= 19


# Quotations


def test_quotes(spark):
    rows = [
        (1, 0, "user", "Hello there\nHow are you?\n\nSecond  para here"), (1, 1, "a", "> how  are YOU?\nFine."), (1, 2, "b", ">> how are you?\n> Fine.\nGood"),
        (1, 3, "c", "> Second para here\r\nyes"), (1, 4, "d", "> unknown text\nno"), (1, 5, None, None), (None, None, "x", "> a"), (1, 3, "c", "dup turn"),
        (2, 1, "u", "> Hello there How are you?\nother conv"), (1, 6, "z", "> Hello there\n> How are you?\n\n> yes\nx"), (1, 5000, "far", "> Good"), (3, 0, "n", ""),
    ]
    got = quotes.link(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")).collect()
    told = sorted(((r["conv_id"], r["turn"], r["reply_to"], r["thread"], r["n_quotes"], r["n_linked"], r["body"]) for r in got), key=str)
    assert told == sorted(
        [
            (1, 0, None, 0, 0, 0, "Hello there\nHow are you?\n\nSecond  para here"), (1, 1, 0, 0, 1, 1, "Fine."), (1, 2, 1, 0, 2, 2, "Good"), (1, 3, 0, 0, 1, 1, "yes"), (1, 3, 0, 0, 0, 1, "dup turn"),
            (1, 4, None, 4, 1, 0, "no"), (1, 5, None, 5, 0, 0, ""), (1, 6, 3, 0, 2, 2, "x"), (1, 5000, 2, 0, 1, 1, "x"[:0]), (2, 1, None, 1, 1, 0, "other conv"), (3, 0, None, 0, 0, 0, ""), (None, None, None, None, 1, 0, ""),
        ],
        key=str,
    )
    ordered = quotes.in_reply_order(quotes.link(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")), 1).collect()
    seen = set()
    for r in ordered:
        assert r["reply_to"] is None or (r["conv_id"], r["reply_to"]) in seen
        seen.add((r["conv_id"], r["turn"]))


def test_trimmed_quotes(spark):
    """Some lines of a paragraph, lines over two paragraphs, one sentence of a line, a sentence wrapped anew: each has its message."""
    rows = [
        (1, 0, "u", "First line\nSecond line\nThird line\n\nNext part"), (1, 1, "u", "One thing is so. Another is not! Last words"), (1, 2, "u", "First line"),
        (1, 3, "a", "> First line\n> Second line\nx"), (1, 4, "a", "> Third line\n> Next part\nx"), (1, 5, "a", "> another is NOT!\nx"), (1, 6, "a", "> Another\n> is not!\nx"),
        (1, 7, "a", "> not said\n> anywhere\nx"), (2, 0, "a", "> Another is not!"),
    ]
    got = quotes.link(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")).where("n_quotes > 0").collect()
    assert {(r["conv_id"], r["turn"]): (r["reply_to"], r["n_linked"]) for r in got} == {(1, 3): (0, 1), (1, 4): (0, 1), (1, 5): (1, 1), (1, 6): (1, 1), (1, 7): (None, 0), (2, 0): (None, 0)}


def brute_links(rows):
    """(conv, turn) -> (reply_to, thread) by a plain walk over each conversation's turns, latest first."""
    def split(text):
        out = []  # (level, lines)
        before = None
        for line in re.split("\r\n?|\n", text or ""):
            mark = re.match(r"[ \t>]*", line)[0]
            level, rest = mark.count(">"), line[len(mark) :].strip(" ")
            if before and before[0] == level and rest and before[1]:
                out[-1][1].append(rest)
            else:
                out.append((level, [rest]))
            before = (level, rest)
        return [(n, [x for x in lines if x]) for n, lines in out if any(lines)]

    def norm(x):
        return re.sub(r"\s+", " ", x.lower()).strip()

    parsed = {(c, t): split(text) for c, t, _, text in rows}
    reply = {}
    for c, t in parsed:
        best = None
        for level, lines in parsed[c, t]:
            if level:
                quote = norm(" ".join(lines))
                for u in sorted((u for d, u in parsed if d == c and u < t), reverse=True):
                    own = [x for n, x in parsed[c, u] if n == 0]
                    if quote in {norm(" ".join(x)) for x in own} | {norm(y) for x in own for y in x}:
                        best = min(best or (level, -u), (level, -u))
                        break
        if best:
            reply[c, t] = -best[1]
    root = {}
    for c, t in parsed:
        at = t
        while (c, at) in reply:
            at = reply[c, at]
        root[c, t] = (reply.get((c, t)), at)
    return root


def test_quotes_against_a_plain_walk(spark):
    """Random conversations; a line of 100,000 marks; messages without conversation or turn; threads put together."""
    r = random.Random(12)
    rows = []
    for c in range(12):
        said = [f"c{c} first words"]
        for t in range(r.randint(1, 30)):
            lines = []
            for _ in range(r.randint(0, 3)):
                lines.append(r.choice([">", "> ", ">> ", " > > "]) + r.choice(said) + r.choice(["", "", " never said"]))
                lines.append(r.choice(["", "then"]))
            own = f"line {r.randrange(40)} of {c}"
            said.append(own)
            rows.append((c, t, "u", "\n".join([*lines, own])))
    want = brute_links(rows)
    odd = [(99, 0, "u", ">" * 100_000), (99, 1, "u", "> " * 50_000 + "deep"), *[(None, n % 5, "u", "> x\ny") for n in range(300)], *[(99, None, None, None)] * 3]
    linked = common.materialise(quotes.link(spark.createDataFrame(rows + odd, "conv_id bigint, turn bigint, role string, text string")), "t")
    got = linked.collect()
    assert len(got) == len(rows) + len(odd)
    assert {(x["conv_id"], x["turn"]): (x["reply_to"], x["thread"]) for x in got if x["conv_id"] is not None and x["conv_id"] < 99} == want
    assert all(x["reply_to"] is None and x["position"] is None for x in got if x["conv_id"] is None or x["turn"] is None)
    for span in (1024, 2):
        whole = {}
        for x in quotes.conversations(linked, span).orderBy("conv_id", "thread", "part").collect():
            assert x["n_rows"] <= span and "> " not in x["chat"]
            whole.setdefault((x["conv_id"], x["thread"]), []).extend(m["turn"] for m in x["messages"])
        assert all(whole[c, root] == sorted(t for (d, t), (_, o) in want.items() if (d, o) == (c, root)) for c, root in {(c, o) for (c, _), (_, o) in want.items()})


def test_quotes_query_is_in_reply_order(spark, sf):
    ordered = queries.QUERIES["op1_quote_links"](spark, sf)
    assert "rangepartitioning(conv_id" in ordered._jdf.queryExecution().toString()
    got = [(r["conv_id"], r["thread"], r["turn"]) for r in ordered.collect()]
    assert len(got) == spark.read.parquet(f"{sf}/conversations.parquet").count()
    known = [x for x in got if None not in x]
    assert known == sorted(known)


def test_quotes_long_chain(spark):
    """A chain of replies over several ranges of turns, each quoting the one before."""
    rows = [(7, n, "u", (f"> line number {n - 1}\n" if n else "") + f"line number {n}") for n in range(2500)]
    got = quotes.link(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string"))
    assert got.where("reply_to = turn - 1 and thread = 0").count() == 2499
    assert quotes.link(spark.createDataFrame([], "conv_id bigint, turn bigint, role string, text string")).count() == 0


# All operators on tables of nothing and of nulls


def test_nothing(spark):
    none = empty(spark)
    assert exact_dedup.classify(none).count() == 0 and exact_dedup.keep_first(none).count() == 0
    assert bpe.encode(none, tokenizers.path("byte_bpe_50k.tiktoken"), tokenizers.PATTERN).count() == 0
    rows, spans = licenses.scan(none)
    assert rows.count() == 0 and spans.count() == 0
    assert mixing.mix(none).count() == 0
