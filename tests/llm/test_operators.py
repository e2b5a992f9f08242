"""Every operator against brute force or an exact round trip, and on nulls, empty and long texts, ties and empty tables."""

from __future__ import annotations

import collections
import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from tileaqp.llm import chat, decontaminate, fingerprints, packing, pii, quality, sharding, simhash_dedup, suffix_dedup, toxicity

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def sentence(rng: random.Random, n: int) -> str:
    return " ".join(rng.choice(WORDS) + str(rng.randrange(50)) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls, empty, white space, copies, near copies, shared passages, one long text, repeated rows, clashing extra columns."""
    rng = random.Random(5)
    texts: list[str | None] = [None, "", " \n\t", "é", "ñandú über 你好 " * 3, "x"]
    base = sentence(rng, 120)
    texts += [base, base, base.upper(), base.replace("alpha", "beta", 1), base + " tail"]
    passage = sentence(rng, 90)
    texts += [sentence(rng, 60) + " " + passage + " " + sentence(rng, 40) for _ in range(5)]
    texts += ["na " * 400, "a" * 1500]
    texts += [sentence(rng, rng.randrange(5, 200)) for _ in range(20)]
    texts.append(sentence(rng, 4000))
    rows = [(i, t, "en", 1.0, "x") for i, t in enumerate(texts)] + [(6, base, "en", 1.0, "x")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, score double, _text string")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.filter("doc_id < 0")


def pairs(df):
    return [(r.doc_id, r.text) for r in df.collect()]


# 1: sharding


@pytest.mark.parametrize("limit", [300, 5_000, 1 << 30])
def test_shards_fit_and_are_the_shortest_prefixes(docs, limit):
    rows = sharding.assign(docs, limit=limit, keep=["doc_id"]).collect()
    assert sorted(r.doc_id for r in rows) == sorted(i for i, _ in pairs(docs))
    size = collections.Counter()
    for r in rows:
        size[r.shard] += r.n_bytes
    for r in rows:
        assert size[r.shard] == r.shard_bytes and (r.shard_bytes <= limit or r.oversized)
        assert r.shard == "" or sum(s for k, s in size.items() if k.startswith(r.shard[:-1])) > limit
    names = sorted(size)
    assert not any(b.startswith(a) for a, b in zip(names, names[1:], strict=False))


def test_a_hot_key_is_split_by_its_rows(spark):
    rows = spark.range(200).select(F.lit(7).cast("long").alias("doc_id"), F.concat(F.lit("text "), F.col("id").cast("string")).alias("text"))
    got = sharding.assign(rows, limit=200).groupBy("shard").agg(F.sum("n_bytes").alias("n")).collect()
    assert len(got) > 5 and max(r.n for r in got) <= 200


def test_columns_named_like_the_result(spark):
    rows = spark.createDataFrame([(i, f"text {i}", "x", 1, 2, "b", 9) for i in range(50)], "doc_id long, text string, shard string, n_bytes int, prefix int, _bits string, _bytes int")
    got = sharding.assign(rows, limit=100)
    assert got.columns == ["doc_id", "text", "prefix", "_bits", "_bytes", *("n_bytes", "shard", "shard_rows", "shard_bytes", "oversized", "shard_depth")]
    assert got.count() == 50 and all(r.n_bytes == len(r.text) and r["_bits"] == "b" and r["_bytes"] == 9 and r.prefix == 2 for r in got.collect())


def test_sharding_empty_and_files(empty, docs, spark, tmp_path):
    assert sharding.assign(empty).count() == 0
    sharding.write(docs, f"{tmp_path}/out", limit=5_000)
    assert spark.read.parquet(f"{tmp_path}/out").count() == docs.count()


# 2: repeated byte strings


def removed(rows, length):
    seen = collections.Counter(b[s : s + length] for _, b in rows for s in range(len(b) - length + 1))
    out = []
    for i, b in rows:
        covered = np.zeros(len(b) + 1, int)
        for s in range(len(b) - length + 1):
            if seen[b[s : s + length]] > 1:
                covered[s] += 1
                covered[s + length] -= 1
        gone = np.cumsum(covered)[: len(b)] > 0
        kept = bytes(np.frombuffer(b, np.uint8)[~gone])
        out.append((i, len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize(("length", "gram", "most"), [(400, 100, 2000), (60, 10, 2000), (60, 10, 1)])
def test_repeats_against_brute_force(docs, length, gram, most, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "MOST_CONTEXTS", most)
    got = suffix_dedup.remove_repeats(docs, length=length, gram=gram).collect()
    want = removed([(i, (t or "").encode()) for i, t in pairs(docs)], length)
    assert sorted(map(tuple, got)) == want


def test_bytes_decide_where_hashes_meet():
    """All windows of eight bytes with weak hashes: only windows whose bytes are elsewhere are hits."""
    rng = random.Random(8)
    contexts = [bytes(rng.choice(b"ab") for _ in range(rng.randrange(8, 40))) for _ in range(12)]
    at = [(k, i) for k, c in enumerate(contexts) for i in range(len(c) - 7)]
    rng.shuffle(at)
    which, start = (np.array(x) for x in zip(*at, strict=True))
    seen = collections.Counter(contexts[k][i : i + 8] for k, i in at)
    lone = np.array([k % 3 > 0 for k in range(12)])
    for weak in (lambda b: zlib.crc32(b) % 7, lambda b: zlib.crc32(b)):
        h = np.array([weak(contexts[k][i : i + 8]) for k, i in at], np.uint64)
        got = suffix_dedup._equal_windows(contexts, which, start, h, lone, 8)
        assert sorted(zip(*map(np.ndarray.tolist, got), strict=True)) == sorted((k, i) for k, i in at if lone[k] and seen[contexts[k][i : i + 8]] > 1)


def test_repeats_in_a_given_table(spark):
    """All documents of a given table against every 400-byte string of theirs."""
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = suffix_dedup.remove_repeats(rows).collect()
    seen, texts = collections.Counter(), [(r.doc_id, (r.text or "").encode()) for r in rows.select("doc_id", "text").collect()]
    for _, b in texts:
        seen.update(hash(b[s : s + 400]) for s in range(len(b) - 399))
    want = []
    for i, b in texts:
        gone = np.zeros(len(b) + 1, int)
        for s in range(len(b) - 399):
            if seen[hash(b[s : s + 400])] > 1:
                gone[s] += 1
                gone[s + 400] -= 1
        gone = np.cumsum(gone)[: len(b)] > 0
        want.append((i, len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest()))
    assert sorted(map(tuple, got)) == sorted(want)


def test_long_texts_are_cut_in_pieces(spark, monkeypatch):
    rng = random.Random(3)
    a = "".join(rng.choice("abcd") for _ in range(3000))
    rows = [(1, a + "q" * 30 + a[500:900]), (2, a[1000:1700]), (3, "unrelated")]
    monkeypatch.setattr(suffix_dedup, "PIECE", 256)
    places = suffix_dedup.anchors(np.frombuffer(a.encode(), np.uint8), 60, 10)[0]
    monkeypatch.setattr(suffix_dedup, "PIECE", 1 << 17)
    assert (places == suffix_dedup.anchors(np.frombuffer(a.encode(), np.uint8), 60, 10)[0]).all()
    got = suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), length=60, gram=10).collect()
    assert sorted(map(tuple, got)) == removed([(i, t.encode()) for i, t in rows], 60)


def test_repeats_empty(empty):
    assert suffix_dedup.remove_repeats(empty).count() == 0


# 3: decontamination


def test_windows_against_brute_force(spark, docs):
    passage = (docs.filter("doc_id = 12").first().text).split()
    items = [(1, " ".join(passage[70:95])), (2, "x"), (3, None), (4, "..."), (5, "never seen in any text at all, not even once, sorry"), (6, "ÑANDÚ Über"), (2, "x"), (7, "ñandú über")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in decontaminate.find(docs, bench).collect()}
    parts = {(r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in decontaminate.find(docs, bench, most=10).collect()}
    want = set()
    for i, t in pairs(docs):
        w = decontaminate.words(t)
        hit, names = set(), set()
        for k, item in items:
            v = decontaminate.words(item)
            for s in range(max(1, len(v) - 9) if v else 0):
                part = v[s : s + 10]
                for at in range(len(w) - len(part) + 1):
                    if w[at : at + len(part)] == part:
                        hit |= set(range(at, at + len(part)))
                        names.add(str(k))
        want.add((i, len(w), len(hit), tuple(sorted(names))))
    assert got == want and parts == want


def test_spans_lie_in_the_original(spark):
    rows = spark.createDataFrame([(1, "Ünï -- ONE, two; Three... four")], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "one two three")], "item_id long, text string")
    r = decontaminate.find(rows, bench).first()
    assert [rows.first().text[s["from"] : s["to"]] for s in r.spans] == ["ONE, two; Three"]
    assert decontaminate.find(rows, bench.filter("item_id < 0")).first().n_hit == 0


# 4 and 6: classifiers


@pytest.mark.parametrize(("method", "label", "least"), [(quality, "quality", 0.95), (toxicity, "toxic", 0.85)])
def test_held_out_accuracy(spark, method, label, least):
    folder = "/root/testdata/sf0.01"
    rows, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    scored = method.score(rows, method.fit(rows, labels, label), column="_s", keep=["doc_id"]).join(labels, "doc_id").filter(quality.held_out(F.col("doc_id"))).toPandas()
    assert ((scored._s >= 0.5) == (scored[label] == 1)).mean() >= least
    assert all(zlib.crc32(str(i).encode()) % 5 == 0 for i in scored.doc_id)


@pytest.mark.parametrize("method", [quality, toxicity])
def test_classifier_edges(spark, docs, empty, method):
    labels = spark.createDataFrame([(i, i % 2, i % 2) for i in range(1, 30)], "doc_id long, quality int, toxic int")
    model = method.fit(docs, labels, "toxic")
    got = method.score(docs, model)
    assert got.columns == [c for c in docs.columns if c != "score"] + ["score"] and got.count() == docs.count()
    assert all(0 <= r.score <= 1 for r in got.collect())
    assert method.score(empty, model).count() == 0
    none = method.fit(docs, labels.filter("doc_id < 0"), "toxic")
    assert {round(r.score, 3) for r in method.score(docs, none).collect()} == {0.5}


def test_toxicity_against_brute_force(spark):
    """Ratios counted one by one, and every score as a plain sum over the text's set of n-grams."""
    rng = random.Random(21)
    texts = [sentence(rng, rng.randrange(3, 40)) + (" awful nasty" if i % 3 == 0 else "") for i in range(120)]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(120)], "doc_id long, toxic int")
    kept = [i for i in range(120) if zlib.crc32(str(i).encode()) % 5]

    def grams(t):
        hashed, _ = toxicity.grams([t])
        return {int(h) for g in hashed for h in g if h >= 0}

    yes, no = collections.Counter(), collections.Counter()
    for i in kept:
        (no if i % 3 else yes).update(grams(texts[i]))
    n_yes = sum(i % 3 == 0 for i in kept)
    n_no = len(kept) - n_yes
    want = {}
    for h in yes.keys() | no.keys():
        a, b = yes[h] + n_yes / len(kept), no[h] + n_no / len(kept)
        r, error = np.log(a / (n_yes + 1)) - np.log(b / (n_no + 1)), np.sqrt(1 / a + 1 / b)
        if abs(r) > 2 * error:
            want[h] = r
    sets = toxicity.feature_sets(quality.training_rows(rows, labels, "toxic", "doc_id", "text", 1000))
    got = toxicity.ratios(sets)
    assert set(np.flatnonzero(got).tolist()) == set(want) and len(want) > 20
    assert all(abs(got[h] - r) < 1e-9 for h, r in want.items())
    weights, bias = toxicity.fit(rows, labels)
    assert set(np.flatnonzero(weights).tolist()) <= set(want)
    for r in toxicity.score(rows, (weights, bias)).collect():
        assert r.score == pytest.approx(1 / (1 + np.exp(-(sum(float(weights[h]) for h in grams(r.text)) + bias))), rel=1e-5)


def test_toxicity_training_against_plain_descent():
    rng = np.random.default_rng(3)
    ratio = np.zeros(1 << toxicity.BITS)
    ratio[:30] = rng.normal(size=30)
    rows = [(np.flatnonzero(rng.random(30) < 0.3).astype(np.int32), int(rng.random() < 0.4)) for _ in range(40)]
    weights, bias = toxicity.train(rows, ratio)
    x = np.array([[ratio[j] if j in set(f.tolist()) else 0.0 for j in range(30)] for f, _ in rows])
    y = np.array([v for _, v in rows], float)
    w, b, gw, gb = np.zeros(30), 0.0, np.full(30, 1e-8), 1e-8
    share = np.where(y == 1, 0.5 / y.sum(), 0.5 / (1 - y).sum())
    for _ in range(120):
        e = (1 / (1 + np.exp(-(x @ w + b))) - y) * share
        d = x.T @ e + 5e-2 * w
        gw, gb = gw + d * d, gb + e.sum() ** 2
        w, b = w - 0.1 * d / np.sqrt(gw), b - 0.1 * e.sum() / np.sqrt(gb)
    assert np.allclose(weights[:30], w * ratio[:30], atol=1e-4) and abs(bias - b) < 1e-4


def test_quality_against_plain_updates(spark):
    """Features token by token, updates coordinate by coordinate, scores as plain sums."""
    import re

    def tokens(text):
        return [m[0] for m in re.finditer(rb"\n+|[0-9]+|[A-Za-z\x80-\xff]+|([\x21-\x7f])\1*", text.encode())]

    texts = ["Two  two!! 12ab\nend", "a, a, a", "", "é ß 9"]
    column = __import__("pyarrow").array(texts)
    from tileaqp.llm import _hashing

    raw, at = _hashing.utf8(column)
    f, o = quality.features(raw, at)
    seen = {}
    for k, t in enumerate(texts):
        part, toks = f[o[k] : o[k + 1]], tokens(t)
        assert len(part) == max(0, 2 * len(toks) - 1)
        names = [("one", x) for x in toks for _ in (0,)]
        pairs_ = [("again",) if a == b else ("two", a, b) for a, b in zip(toks, toks[1:], strict=False)]
        for name, h in [*zip(names, part[0::2].tolist(), strict=True), *zip(pairs_, part[1::2].tolist(), strict=True)]:
            assert seen.setdefault(name, h) == h
    assert len(set(seen.values())) == len(seen)
    rows = [(np.array(f[o[k] : o[k + 1]]), k % 2) for k in range(4)]
    weights, bias = quality.train(iter(rows), epochs=2)
    z, n, last = collections.Counter(), collections.Counter(), 1 << quality.BITS

    def weight(i):
        return 0.0 if abs(z[i]) <= 0.1 else -(z[i] - np.sign(z[i]) * 0.1) / (1 + np.sqrt(n[i]) + 0.1)

    order = np.random.default_rng(5)
    for _ in range(2):
        for k in order.permutation(4):
            ids = collections.Counter(rows[k][0].tolist())
            x = {i: c / max(1.0, np.sqrt(sum(ids.values()))) for i, c in ids.items()} | {last: 1.0}
            w = {i: weight(i) for i in x}
            g = 1 / (1 + np.exp(-sum(w[i] * x[i] for i in x))) - rows[k][1]
            for i in x:
                step = g * x[i]
                z[i] += step - (np.sqrt(n[i] + step * step) - np.sqrt(n[i])) * w[i]
                n[i] += step * step
    assert bias == pytest.approx(weight(last)) and all(weights[i] == pytest.approx(weight(i), abs=1e-6) for i in z if i != last)
    got = quality.score_texts(column, weights, bias)
    for k in range(4):
        total = sum(float(weights[i]) for i in rows[k][0].tolist()) / max(1.0, np.sqrt(len(rows[k][0])))
        assert got[k] == pytest.approx(1 / (1 + np.exp(-(bias + total))), rel=1e-5)


def test_training_rows_are_bounded_and_the_same(spark):
    rows = spark.createDataFrame([(i % 40, f"text {i} " * 20) for i in range(200)] + [(100, "x" * 5000), (101, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1) for i in (*range(40), 100, 101)] + [(3, 0), (None, 1)], "doc_id long, quality int")
    got = [tuple(r) for r in quality.training_rows(rows, labels, "quality", "doc_id", "text", 20, 3000).collect()]
    again = [tuple(r) for r in quality.training_rows(rows.repartition(7), labels, "quality", "doc_id", "text", 20, 3000).collect()]
    assert sorted(got) == sorted(again) and 5 < len(got) <= 20 and sum(len(t) for t, _ in got) <= 3000


# 5: SimHash


def fingerprint(text, k):
    w = (text or "").encode().lower().split()
    h = [xxh64_intdigest(b" ".join(w[i : i + k]), 42) for i in range(max(1, len(w) - k + 1))] if w else []
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def reach(nodes, linked):
    parent = {n: n for n in nodes}

    def root(n):
        while parent[n] != n:
            n = parent[n]
        return n

    for a, b in linked:
        parent[max(root(a), root(b))] = min(root(a), root(b))
    return {n: root(n) for n in nodes}


def test_components_against_all_pairs(docs):
    got = simhash_dedup.components_of(docs).collect()
    prints = {(i, t): fingerprint(t, 4) for i, t in pairs(docs)}
    assert all(prints[i, t] == next(r.fp for r in got if r.doc_id == i) % (1 << 64) for i, t in pairs(docs))
    keys = [(i, f) for (i, _), f in prints.items()]
    want = reach([i for i, _ in keys], [(i, j) for i, f in keys for j, g in keys if i < j and (f ^ g).bit_count() <= 4])
    assert {r.doc_id: r.component for r in got} == want and len(got) == docs.count()


def test_links_keep_all_components_of_dense_groups(spark, monkeypatch):
    rng = random.Random(1)
    centres = [rng.getrandbits(64) for _ in range(4)]
    fps = {c ^ sum(1 << b for b in rng.sample(range(64), rng.randrange(6))) for c in centres for _ in range(150)}
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    frame = spark.createDataFrame([(f,) for f in signed], "fp long")
    want = reach(signed, [(a, b) for a in signed for b in signed if a < b and ((a ^ b) & (1 << 64) - 1).bit_count() <= 4])
    for block in (4096, 16):
        monkeypatch.setattr(simhash_dedup, "BLOCK", block)
        found = {r.node: r.root for r in simhash_dedup.components(simhash_dedup.links(frame)).collect()}
        assert all(found.get(n, n) == r for n, r in want.items())


def test_near_duplicates_by_shingles(docs, empty):
    got = {r.doc_id: r.component for r in simhash_dedup.near_duplicates(docs).collect()}
    shingles = {i: set(simhash_dedup.shingle_hashes(t, 5).tolist()) for i, t in pairs(docs)}
    linked = [(a, b) for a, x in shingles.items() for b, y in shingles.items() if a < b and (len(x & y) >= 0.8 * len(x | y))]
    assert got == reach(list(shingles), linked)
    assert simhash_dedup.near_duplicates(empty).count() == 0 and simhash_dedup.components_of(empty).count() == 0


def near_against_all_pairs(spark, texts):
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.component for r in simhash_dedup.near_duplicates(frame).collect()}
    shingles = [set(simhash_dedup.shingle_hashes(t, 5).tolist()) for t in texts]
    sizes = [(a, b, len(x & y), len(x | y)) for a, x in enumerate(shingles) for b, y in enumerate(shingles) if a < b and x & y]
    assert got == reach(range(len(texts)), [(a, b) for a, b, both, either in sizes if both >= 0.8 * either])
    return sizes


def fresh(rng, n):
    return [f"w{rng.randrange(1 << 40)}" for _ in range(n)]


@pytest.mark.parametrize("block", [4096, 50])
def test_near_duplicates_of_a_star(spark, monkeypatch, block):
    """Copies near one original, and near each other in few cases."""
    monkeypatch.setattr(simhash_dedup, "BLOCK", block)
    rng = random.Random(11)
    original = fresh(rng, 304)
    texts = []
    for _ in range(300):
        w = original[:]
        for at in rng.sample(range(4, 300, 5), 6):
            w[at] = fresh(rng, 1)[0]
        texts.append(" ".join(w))
    texts.insert(150, " ".join(original))
    near_against_all_pairs(spark, texts)


def test_near_duplicates_by_containment(spark):
    """Truncated copies just above and below the similarity, longer than any sketch."""
    rng = random.Random(12)
    texts = []
    for share in (0.79, 0.8, 0.82, 0.85):
        for _ in range(15):
            w = fresh(rng, 1004)
            texts += [" ".join(w), " ".join(w[: int(share * 1000) + 4])]
    assert sum(both >= 0.8 * either for *_, both, either in near_against_all_pairs(spark, texts)) == 45


def test_near_duplicates_at_the_very_similarity(spark):
    """Long texts that miss or reach the similarity by one shingle."""
    rng = random.Random(13)
    texts = []
    for missing in (0, 1):
        for _ in range(25):
            w = fresh(rng, 1804)
            texts += [" ".join(w), " ".join(w[: 1444 - missing])]
    assert sum(both >= 0.8 * either for *_, both, either in near_against_all_pairs(spark, texts)) == 25


def test_near_duplicates_with_repeated_lines(spark):
    rng = random.Random(14)
    texts = []
    for _ in range(40):
        w, line = fresh(rng, 1000), fresh(rng, 12)
        texts += [" ".join(w + line), " ".join(w + line * 200)]
    assert sum(both >= 0.8 * either for *_, both, either in near_against_all_pairs(spark, texts)) == 40


def test_pipeline_links_by_fingerprints_and_by_shingles(spark):
    """Pairs that only one of the two links, and a chain of both."""
    import corpus_pipeline

    rng = random.Random(16)
    line, base = fresh(rng, 13), fresh(rng, 400)
    a, b = (" ".join(line * 200 + fresh(rng, 100)) for _ in range(2))  # the line's votes outweigh the rest
    long, cut = " ".join(base), " ".join(base[:330])
    far = lambda x, y: (fingerprint(x, 4) ^ fingerprint(y, 4)).bit_count()
    assert far(a, b) <= 4 < far(long, cut)
    c = " ".join(a.split()[: -20])
    frame = spark.createDataFrame(list(enumerate([b, a, c, long, cut, " ".join(fresh(rng, 50))])), "doc_id long, text string")
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, frame, "").collect()) == [0, 3, 5]


@pytest.mark.parametrize("finish", [1 << 18, 6, 0])
def test_components_in_one_task_and_in_rounds(spark, monkeypatch, finish):
    monkeypatch.setattr(simhash_dedup, "FINISH", finish)
    rng = random.Random(17)
    way = rng.sample(range(1000, 2000), 40)
    edges = [*zip(way, way[1:], strict=False), *((-7, x) for x in range(20)), (-50, 60), (60, -50), (3000, 3000)]
    got = {r.node: r.root for r in simhash_dedup.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == reach(sorted({x for e in edges for x in e}), edges)
    named = spark.createDataFrame([(bytes([a % 251, 200]), bytes([b % 251])) for a, b in edges], "a binary, b binary")
    got = {bytes(r.node): bytes(r.root) for r in simhash_dedup.components(named).collect()}
    linked = [(bytes(a), bytes(b)) for a, b in named.collect()]
    assert got == reach(sorted({x for e in linked for x in e}), linked)


def test_keys_of_fingerprints_are_not_broadcast(spark, tmp_path):
    spark.range(2000).selectExpr("xxhash64(id) AS fp").write.parquet(str(tmp_path / "prints"))
    found = simhash_dedup.links(spark.read.parquet(str(tmp_path / "prints")))
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.count() == 0


def test_components_of_few_links_take_few_jobs(spark):
    """Every job's plan and tasks stay in the driver's memory."""
    edges = spark.createDataFrame([(i, i + 1) for i in range(200)], "a long, b long")
    spark.sparkContext.setJobGroup("components", "")
    try:
        assert {r.root for r in simhash_dedup.components(edges).collect()} == {0}
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("components")) <= 6
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_rows_that_repeat_an_id_or_have_none(spark):
    import corpus_pipeline

    rng = random.Random(15)
    a, b, c = (" ".join(fresh(rng, 50)) for _ in range(3))
    rows = [(1, a, 1), (1, b, 1), (2, b, 1), (1, a, 1), (1, a, 2), (None, a, 1), (None, c, 1), (None, c, 1), (None, None, 1), (3, "", 1)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, n int")
    got = [tuple(r) for r in corpus_pipeline.drop_near_duplicates(spark, frame, "").collect()]
    assert sorted(got, key=str) == sorted([(1, a, 1), (1, b, 1), (None, c, 1), (3, "", 1)], key=str)


# 7: personal data


def test_surrogates(spark, empty):
    texts = [
        "Mr. John Smith met Mrs. Anna Smith; mail A.B@Mail.Example.com or a.b@mail.example.com!",
        "card 4111 1111 1111 1111, again 4111-1111-1111-1111; +1 (974) 555-3436 10.0.0.1. 123-45-6789",
        "Госпожа Иванова и Господин Иванов \x01 \x02a\x03 DE89 3704 0044 0532 0130 00",
        'TOKEN = "24BE64439E3E49CF46B2D7C90F3602A3D0B907FF" token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"',
        "nothing here", None, "", "10.0.0.1 10.0.0.2 " + " ".join(f"10.1.{i}.7" for i in range(200)),
    ]
    rows = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, mention string")
    out = {r.doc_id: r for r in pii.replace(rows, "secret").collect()}
    assert out[4].text == "nothing here" and out[5].text is None and out[6].text == "" and out[0].mention == "x"
    for gone in ("Smith", "Mail.Example", "mail.example"):
        assert gone not in out[0].text
    assert out[0].text.startswith("Mr. ") and " met Mrs. " in out[0].text and out[0].text.endswith("!")
    cards = [x.replace(" ", "").replace("-", "") for x in (out[1].text[5:24], out[1].text[32:51])]
    assert cards[0] == cards[1] and cards[0] != "4" + "1" * 15 and luhn(cards[0])
    assert "\x01 \x02a\x03" in out[2].text and "Иванов" not in out[2].text and "ова" in out[2].text
    upper, lower = out[3].text.split('"')[1], out[3].text.split('"')[3]
    assert upper == lower.upper() and len(lower) == 40 and lower != "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"
    addresses = out[7].text.split()
    assert len(set(addresses)) == 202 and not set(addresses) & set(texts[7].split()) and addresses[0] in out[1].text
    assert out[1].n_entities == 5 and pii.replace(empty, "k").count() == 0
    other = {r.doc_id: r.text for r in pii.replace(rows, "another").collect()}
    assert other[0] != out[0].text


def luhn(digits: str) -> bool:
    return sum(sum(divmod(int(d) * (1 + i % 2), 10)) for i, d in enumerate(reversed(digits))) % 10 == 0


def test_names_keep_surname_case_and_gender(spark):
    rows = [
        "Mr. John Smith met Mr. Smith and Dr. Smith, Mr. JOHN SMITH's dog. Ms. Anna Weber, Dr. Anna Weber; Dr. Robin O'Neil-Jones",
        "Госпожа Анна Иванова и Господин Иванов, Κυρία Παπαδοπούλου Κύριος Παπαδόπουλος",
        "v1.2.3.4 order 1234567890123 fe80::1ff:fe23:4567:890a FE80::1FF:FE23:4567:890A 300.1.1.1",
    ]
    frame = spark.createDataFrame([(i, t, 1, 2) for i, t in enumerate(rows)], "doc_id long, text string, _pii_ int, _pii_map int")
    got = {r.doc_id: r for r in pii.replace(frame, "k").collect()}
    assert got[0].n_entities == 7 and got[0]["_pii_"] == 1 and got[0]["_pii_map"] == 2
    w = got[0].text.replace(",", "").replace(".", "").replace(";", "").split()
    first, last = w[1], w[2]
    assert last not in ("Smith", first) and w[5] == last and w[8] == last and w[10:12] == [first.upper(), f"{last.upper()}'s"]
    assert w[13] == "Ms" and w[14:16] == w[17:19] and w[14].endswith("na") and first.endswith("n")
    assert "Smith" not in got[0].text and "SMITH" not in got[0].text and "O'Neil" not in got[0].text
    words = got[1].text.replace(",", "").split()
    assert words[2].endswith("ова") and words[5].endswith("ов") and words[2][:-1] == words[5] and words[7].endswith("ου") and words[9].endswith("ος") and words[7][:-2] == words[9][:-2]
    assert got[2].text.startswith("v1.2.3.4 order 1234567890123 ") and got[2].text.endswith(" 300.1.1.1")
    low, high = got[2].text.split()[3:5]
    assert low.upper() == high and low != "fe80::1ff:fe23:4567:890a" and low.count(":") == 5


def test_query_against_a_plain_search(spark):
    """All of a given table: the same mentions found by another engine, everything else unchanged, one surrogate for each entity and format kept."""
    import regex

    from tileaqp.llm import queries

    folder = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in queries.op7_pii(spark, folder).collect()}
    any_ = regex.compile("|".join(f"(?P<{k}>{p})" for k, p in pii.KINDS.items()))
    texts = [(r.doc_id, r.text) for r in spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect()]
    made, back, seen = {}, {}, 0
    for i, t in texts:
        found = list(any_.finditer(t))
        assert got[i].n_entities == len(found)
        new, at = got[i].text, 0
        for k, m in enumerate(found):
            gap = t[found[k - 1].end() if k else 0 : m.start()]
            assert new.startswith(gap, at)
            at += len(gap)
            after = t[m.end() : found[k + 1].start() if k + 1 < len(found) else len(t)]
            end = len(new) if k + 1 == len(found) and not after else new.index(after, at + 1) if after else at + len(m[0])
            put, at = new[at:end], end
            seen += 1
            assert put != m[0] and put == made.setdefault(m[0], put)
            core = regex.sub(r"[ .()+:-]", "", m[0]).lower() if m.lastgroup in ("phone", "card", "ssn", "iban") else m[0].lower()
            same = regex.sub(r"[ .()+:-]", "", put).lower() if m.lastgroup in ("phone", "card", "ssn", "iban") else put.lower()
            assert back.setdefault((m.lastgroup, same), core) == core
            if m.lastgroup in ("phone", "card", "ssn", "iban"):
                assert regex.sub(r"[0-9A-Z]", "x", put) == regex.sub(r"[0-9A-Z]", "x", m[0])
        assert found or new == t
    assert seen > 50


def test_more_names_than_short_surrogates(spark):
    entities = spark.range(30_000).select(F.lit("name").alias("kind"), F.concat(F.lit("n"), "id").alias("value"))
    got = pii.distinct_surrogates(entities, "k")
    assert got.select("made").distinct().count() == 30_000


def test_clashing_surrogates_are_drawn_again(spark, monkeypatch):
    from pyspark.sql import functions as G

    def narrow(kind, value, attempt, key):
        return G.pmod(G.xxhash64(value, attempt), G.lit(40)).cast("string")

    monkeypatch.setattr(pii, "surrogate", narrow)
    entities = spark.createDataFrame([("ip", f"v{i}") for i in range(25)] + [("ip", "7")], "kind string, value string")
    made = [r.made for r in pii.distinct_surrogates(entities, "k").collect()]
    assert len(made) == len(set(made)) == 26 and "7" not in made


# 8: packing


def test_packing(docs, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    got = packing.pack_documents(docs, ids=True).collect()
    ids = {i: t.encode(x or "", add_special_tokens=False).ids + [2] for i, x in pairs(docs)}
    by = collections.defaultdict(list)
    for r in got:
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert part == r.ids and zlib.crc32(np.array(part, "<u4").tobytes()) == r.ids_crc32
        assert r.length <= 1024 and (r.piece == 0 or r.length == 1024)
        by[r.sequence_id].append((r.offset, r.length))
    for spans in by.values():
        at = 0
        for offset, n in sorted(spans):
            assert offset == at
            at += n
        assert at <= 1024
    total = sum(len(ids[i]) for i, _ in pairs(docs))
    assert sum(r.length for r in got) == total and len(by) <= -(-total // 1024) + 1
    assert packing.pack_documents(empty).count() == 0


def test_later_rounds_of_packing_read_little(spark):
    """Bins that nothing can join end at once; quality stays that of best fit in one place."""
    rng = random.Random(6)
    sizes = [600] * 4000 + [rng.randrange(1, 1024) for _ in range(3000)] + [100] * 40
    items = spark.createDataFrame(list(enumerate(sizes)), "uid long, length long").repartition(32)
    got = packing.pack(items).collect()
    fill = collections.Counter()
    for r in got:
        fill[r.sequence_id] += sizes[r.uid]
    assert len(got) == len(sizes) and max(fill.values()) <= 1024
    assert len(fill) <= 1.02 * len(packing.best_fit(np.array(sizes), 1024)) and sum(2 * f <= 1024 for f in fill.values()) <= 1


def test_other_vocabulary_gives_the_same_ids(docs):
    import public_tokenizers

    a = packing.pieces(docs).drop("uid").collect()
    b = packing.pieces(docs, vocabulary_path=public_tokenizers.path("byte_bpe_50k.json")).drop("uid").collect()
    assert sorted(a) == sorted(b)


def test_special_strings_are_ordinary_text(spark):
    rows = spark.createDataFrame([(1, "a <|endoftext|> b")], "doc_id long, text string")
    import public_tokenizers

    a = packing.pieces(rows).first().ids_crc32
    assert a == packing.pieces(rows, vocabulary_path=public_tokenizers.path("byte_bpe_50k.json")).first().ids_crc32


# 9: fingerprints


def test_edits_and_neighbours(spark, docs, empty, monkeypatch):
    rows = docs.dropDuplicates(["doc_id"])
    got = {r.doc_id: r for r in fingerprints.fingerprints_and_edits(rows).collect()}
    order = sorted(pairs(rows), reverse=True, key=lambda p: p[0])
    for k, (i, t) in enumerate(order):
        t, nxt = t or "", order[(k + 1) % len(order)][1] or ""
        cut = len(t) // 3
        assert got[i].n_chars == len(t) and got[i].edited_sha256 == hashlib.sha256((t[: len(t) - cut] + nxt[:cut]).encode()).hexdigest()
        other = got[order[(k + 1) % len(order)][0]].fp
        assert got[i].near_next == pytest.approx(1 - ((got[i].fp ^ other) & (1 << 64) - 1).bit_count() / 64)
    assert got[6].fp == got[7].fp and got[0].fp == got[1].fp == 0
    assert fingerprints.fingerprints_and_edits(empty).count() == 0
    single = fingerprints.fingerprints_and_edits(rows.filter("doc_id = 6")).first()
    assert single.near_next == 1.0


def test_repeated_and_null_keys_of_fingerprints(spark, docs):
    rows = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(None, "lost"), (None, "lost too")], "doc_id long, text string"))
    assert fingerprints.fingerprints_and_edits(rows).count() == rows.count()


def vote_of(text):
    """The fingerprint by counting every bit's votes one by one."""
    import xxhash

    w = [x for x in (text or "").translate(str.maketrans("\n\t\r\x0b\x0c", "     ")).split(" ") if x]
    votes, weight = [0] * 64, 0
    for a, b in zip(w, [*w[1:], None], strict=True):
        h = xxhash.xxh64_intdigest(a.encode(), 42)
        h = h if b is None else xxhash.xxh64_intdigest(b.encode(), h)
        n = len(a) + len(b or "")
        weight += n
        votes = [v + n * (h >> i & 1) for i, v in enumerate(votes)]
    f = sum(1 << i for i, v in enumerate(votes) if 2 * v > weight)
    return f - (1 << 64) if f >> 63 else f


def test_votes_of_a_given_table(spark):
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    got = {r.doc_id: r for r in fingerprints.fingerprints_and_edits(rows).collect()}
    order = sorted(pairs(rows), reverse=True)
    for k, (i, t) in enumerate(order):
        nxt = order[(k + 1) % len(order)][1]
        cut = len(t) // 3
        edited = t[: len(t) - cut] + nxt[:cut]
        assert got[i].fp == vote_of(t) and got[i].edited_fp == vote_of(edited)
        assert got[i].near_edited == pytest.approx(1 - ((got[i].fp ^ got[i].edited_fp) & (1 << 64) - 1).bit_count() / 64)
    named = rows.select(F.col("doc_id").cast("string").alias("doc_id"), "text")
    assert {r.doc_id: r.fp for r in fingerprints.fingerprints_and_edits(named).collect()} == {str(i): r.fp for i, r in got.items()}


def test_search_query_against_all_pairs(spark):
    from tileaqp.llm import queries

    folder = "/root/testdata/sf0.001"
    docs_ = spark.read.parquet(f"{folder}/documents.parquet")
    fps = {r.doc_id: vote_of(r.text) for r in docs_.collect()}
    want = {(a, b) for i, a in fps.items() if i % 20 == 0 for b in fps.values() if ((a ^ b) & (1 << 64) - 1).bit_count() <= 3}
    assert {(r.fp, r.other) for r in queries.fingerprint_neighbours(spark, folder).collect()} == want


def test_block_tables_find_everything(spark):
    rng = random.Random(2)
    base = [rng.getrandbits(64) - (1 << 63) for _ in range(60)]
    fps = base + [b ^ sum(1 << x for x in rng.sample(range(63), rng.randrange(1, 6))) for b in base]
    frame = spark.createDataFrame([(f,) for f in fps], "fp long")
    for radius in (0, 3, 5, 6):
        got = sorted(map(tuple, fingerprints.within(frame, frame, radius).collect()))
        want = sorted((a, b, d) for a in set(fps) for b in set(fps) if (d := ((a ^ b) & (1 << 64) - 1).bit_count()) <= radius)
        assert got == want


# 10: chat


def test_templates_round_trip():
    rng = random.Random(4)
    for _ in range(300):
        turns = [("".join(rng.choice("ab:\\#\n<") for _ in range(rng.randrange(5))), "".join(rng.choice(["\\", "#", "</turn>", "\n", "###", " a", ": ", "</turn"]) for _ in range(rng.randrange(8)))) for _ in range(rng.randrange(4))]
        turns.append(("assistant", turns[0][1] if turns else ""))
        text, mask = chat.format_turns(turns)
        assert chat.read_turns(text) == turns
        assert [chat.unescape(text[a:b]) for a, b in mask] == [t for r, t in turns if r == "assistant"]


def test_best_branches_of_reply_trees(spark):
    rows = [(1, 1, None, "user", "q", 0.0), (1, 2, 1, "assistant", "bad", 0.1), (1, 3, 1, "assistant", "good", 0.9), (1, 4, 3, "user", "more", 0.5), (1, 5, 4, "assistant", "end", 1.0), (1, 6, 3, "user", "other", 0.2), (2, 1, None, "user", None, None), (2, 2, 9, "user", "orphan", 0.0)]
    tree = spark.createDataFrame(rows, "tree long, node long, parent long, role string, text string, score double")
    got = {(r.tree, r.branch): [t for _, t in chat.read_turns(r.formatted)] for r in chat.conversations(tree, best=2).collect()}
    assert got[1, 1] == ["q", "good", "more", "end"] and got[1, 2] == ["q", "good", "other"]
    assert sorted([got[2, 1], got[2, 2]]) == [[""], ["orphan"]]
    assert chat.conversations(tree.filter("tree = 0")).count() == 0
    cycle = spark.createDataFrame([(1, 1, 2, 0.0), (1, 2, 1, 0.0), (1, 3, 1, 0.0), (2, 1, None, 0.0), (2, 2, 1, 0.0)], "tree long, node long, parent long, score double")
    assert {(r.tree, r.node) for r in chat.paths(cycle).collect()} == {(2, 1), (2, 2)}


def test_long_and_null_conversations(spark):
    rows = [(1, i, "user" if i % 2 == 0 else "assistant", f"turn {i}") for i in range(70)] + [(None, 0, None, None), (None, 0, "assistant", "a"), (3, 1, "assistant", "same"), (3, 1, "assistant", "same")]
    messages = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.tree: r for r in chat.read_back(chat.conversations(chat.linear(messages))).collect()}
    assert got[1].n_turns == 70 and got[None].n_turns == 2 and got[3].loss_chars == 8
    assert got[1].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for _, _, r, t in rows[:70]).encode()).hexdigest()
