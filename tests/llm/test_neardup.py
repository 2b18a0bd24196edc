import math
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from roadweave.llm import kernel, neardup

WORD = re.compile(r"[^\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]+")


def grams(text):
    words = WORD.findall((text or "").lower())
    if len(words) < neardup.WIDTH:
        return Counter({tuple(words): 1}) if words else Counter()
    return Counter(tuple(words[i : i + neardup.WIDTH]) for i in range(len(words) - neardup.WIDTH + 1))


def hash_of(gram):
    """The kernel's hash of one shingle."""
    data = np.frombuffer(" ".join(gram).encode(), np.uint8)
    offsets = np.array([0, len(data)])
    starts, ends, rows = kernel.words(data, offsets, kernel.NOT_WORD)
    return kernel.shingles(kernel.word_hashes(data, starts, ends), rows, neardup.WIDTH)[0][0]


def brute(texts):
    """Classes of all pairs whose weighted Jaccard similarity is enough."""
    bags = [grams(t) for t in texts]
    code = {g: int(hash_of(g) >> np.uint64(40)) % neardup.DF_BUCKETS for g in set().union(*bags)}
    total = Counter(code[g] for b in bags for g in b)
    every, n = sum(total.values()), max(1, sum(bool(b) for b in bags))
    idf = {}
    for g, c in code.items():
        df = max(1.0, total[c] - (every - total[c]) / (neardup.DF_BUCKETS - 1))
        idf[g] = (1 + math.log((1 + n) / (1 + min(df, n))) / math.log(1 + n)) ** neardup.DAMPING
    sets = [{g: (1 + math.log(c)) * idf[g] for g, c in b.items()} for b in bags]
    parent = list(range(len(texts)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            both = sets[i].keys() & sets[j].keys()
            if not both:
                continue
            low = sum(min(sets[i][g], sets[j][g]) for g in both)
            if low / (sum(sets[i].values()) + sum(sets[j].values()) - low) >= neardup.SIMILARITY:
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return [root(i) for i in range(len(texts))]


def changed(rng, text, share):
    return " ".join(f"new{rng.randrange(10**6)}" if rng.random() < share else w for w in text.split())


def corpus():
    rng = random.Random(5)
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(900)]
    base = [" ".join(rng.choice(words) for _ in range(rng.randint(5, 160))) for _ in range(70)]
    passage = " ".join(rng.choice(words) for _ in range(60))
    texts = base + [f"{t} {passage}" for t in base[:25]]
    texts += [changed(rng, rng.choice(base), rng.choice([0.004, 0.01, 0.02, 0.04])) for _ in range(120)]
    texts += [base[3].upper(), base[3] + " !!", "", None, "?!", "two words", "Two  words.", "word " * 400, "word " * 300]
    hub = " ".join(rng.choice(words) for _ in range(150))
    return texts + [hub] + [changed(rng, hub, 0.015) for _ in range(40)]


def test_classes_against_brute_force(spark):
    texts = corpus()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in neardup.classes(docs).collect()}
    expected = brute(texts)
    assert len(got) == len(texts)
    wrong = [i for i in range(len(texts)) if got[i]["class_id"] != expected[i]]
    assert len(wrong) <= 0.01 * len(texts), wrong
    sizes = Counter(r["class_id"] for r in got.values())
    assert all(r["class_size"] == sizes[r["class_id"]] and r["kept"] == (r["doc_id"] == r["class_id"]) for r in got.values())


def test_samples_agree_as_often_as_texts_are_similar():
    rng = np.random.default_rng(1)
    n = 400
    h = kernel.mix(np.arange(1, n + 1, dtype=np.uint64))
    a, b = rng.uniform(1, 2, n), rng.uniform(1, 2, n)
    a[:60], b[60:120] = 1e-9, 1e-9
    keep_a, keep_b = a > 1e-6, b > 1e-6
    keys = neardup.band_keys(np.concatenate([h[keep_a], h[keep_b]]), np.concatenate([a[keep_a], b[keep_b]]), np.array([keep_a.sum(), keep_b.sum()]), bands=4000, rows=1)
    true = np.minimum(a, b)[keep_a & keep_b].sum() / np.maximum(np.where(keep_a, a, 0), np.where(keep_b, b, 0)).sum()
    assert abs((keys[0] == keys[1]).mean() - true) < 0.03


def test_similarity_of_a_pair():
    idf = np.ones(8)
    s = neardup.similarities(pa.array(["a b c d e f", "a", "", "x y"]), pa.array(["a b c d e g", "a", "", "y x"]), idf, 5)
    assert np.allclose(s, [1 / 3, 1, 0, 0])


def test_odd_rows(spark, odd_docs):
    got = neardup.classes(odd_docs)
    assert got.count() == odd_docs.count()
    kept = neardup.drop_near(odd_docs.withColumn("kept", F.lit("x")))
    assert kept.columns == [*odd_docs.columns, "kept"]
    assert kept.where("text = 'one two three'").count() == 1
    empty = spark.createDataFrame([], "doc_id long, text string, kept int")
    assert neardup.classes(empty).count() == 0 and neardup.drop_near(empty).count() == 0


def test_every_similar_pair_of_a_bucket_is_found(spark):
    """Many texts share a long passage and meet in few, large buckets, whose leaders are like none of them."""
    rng = random.Random(11)
    passage = " ".join(f"p{i}" for i in range(140))
    texts = [f"{passage} " + " ".join(f"w{i}x{j}" for j in range(45)) for i in range(60)]
    texts += [changed(rng, t, 0.012) for t in texts[:30]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    idf = spark.sparkContext.broadcast(neardup.document_frequencies(docs))
    signed = neardup.signatures(docs, idf, id_col="doc_id", text_col="text", width=neardup.WIDTH, bands=2, rows=1).collect()
    keys = {r["doc_id"]: r["bands"] for r in signed}
    pairs = [(i, j) for i in range(len(texts)) for j in range(i) if any(a == b for a, b in zip(keys[i], keys[j]))]
    s = neardup.similarities(pa.array([texts[i] for i, _ in pairs]), pa.array([texts[j] for _, j in pairs]), idf.value, neardup.WIDTH)
    similar = [p for p, x in zip(pairs, s) if x >= neardup.SIMILARITY]
    assert len(pairs) > 300 and 10 < len(similar) < 40
    of = {r["doc_id"]: r["class_id"] for r in neardup.classes(docs, bands=2, rows=1).collect()}
    assert [p for p in similar if of[p[0]] != of[p[1]]] == []


def test_prefixes_of_similar_texts_meet():
    texts = corpus()[:190]
    rng = np.random.default_rng(3)
    idf = rng.uniform(1, 2, 64)
    column = pa.array([t or "" for t in texts])
    found, counts, _ = neardup.prefixes(column, idf, similarity=neardup.SIMILARITY, width=neardup.WIDTH)
    own = [set(x.tolist()) for x in np.split(found, np.cumsum(counts)[:-1])]
    pairs = [(i, j) for i in range(len(texts)) for j in range(i)]
    s = neardup.similarities(column.take([i for i, _ in pairs]), column.take([j for _, j in pairs]), idf, neardup.WIDTH)
    similar = [p for p, x in zip(pairs, s) if x >= neardup.SIMILARITY]
    assert len(similar) > 20 and all(own[i] & own[j] for i, j in similar)


def test_tiles_leaders_and_prefixes_change_no_class(spark):
    """Small tiles and few queries a bucket send the texts along every way there is."""
    docs = spark.createDataFrame(list(enumerate(corpus())), "doc_id long, text string")
    plain = {r["doc_id"]: r["class_id"] for r in neardup.classes(docs, bands=30, rows=1).collect()}
    for tile, wide in ((4, 10**6), (16, 3), (512, 0)):
        assert {r["doc_id"]: r["class_id"] for r in neardup.classes(docs, bands=30, rows=1, tile=tile, wide=wide).collect()} == plain


def test_tile_against_pairs():
    rng = random.Random(2)
    base = " ".join(f"b{i}" for i in range(90))
    texts = [changed(rng, base, 0.02) for _ in range(40)] + ["", "b1 b2", "b1 b2"]
    column = pa.array(texts)
    idf = np.random.default_rng(4).uniform(1, 2, 64)
    hashes, weights, counts, _, _ = neardup.weighted_sets(column, idf, neardup.WIDTH)
    c = np.array([i // 2 for i in range(len(texts))])
    member, query = np.arange(len(texts)) % 5 > 0, np.arange(len(texts)) % 3 > 0
    a, b = neardup.tile_links(c, member, query, counts, hashes, weights, neardup.SIMILARITY)
    pairs = [(q, m) for q in np.flatnonzero(query) for m in np.flatnonzero(member) if c[q] != c[m]]
    s = neardup.similarities(column.take([q for q, _ in pairs]), column.take([m for _, m in pairs]), idf, neardup.WIDTH)
    expected = {(c[q], c[m]) for (q, m), x in zip(pairs, s) if x >= neardup.SIMILARITY}
    assert set(zip(a.tolist(), b.tolist())) == expected and 20 < len(expected) < len(pairs)
