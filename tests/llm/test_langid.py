import math
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from roadweave.llm import langid


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.predict(docs).where("held_out").join(docs.select("doc_id", "lang"), "doc_id")
    right, n = got.agg(F.sum((F.col("lang") == F.col("lang_pred")).cast("int")), F.count("*")).first()
    assert n > 200 and right >= 0.98 * n
    assert got.where("rejected").count() <= 0.01 * n


def words(text):
    """Words as the model reads them, by plain means."""
    out, run = [], ""
    for c in text + " ":
        if c.isalpha() or c.isdigit():
            run += c
        elif run:
            if not any(x.isdigit() for x in run):
                out.append("".join(x.lower()[0] for x in run))
            run = ""
    return out


def kneser_ney(texts):
    """Probability function of plain dictionaries; ends of words are NUL."""
    full = Counter()
    for t in texts:
        for w in words(t):
            padded = "\0" * (langid.ORDER - 1) + w + "\0"
            for i in range(langid.ORDER - 1, len(padded)):
                full[padded[i - langid.ORDER + 1 : i + 1]] += 1
    levels, raw = [full], full
    for k in range(langid.ORDER - 1, 0, -1):
        kinds, total = Counter(), Counter()
        for g, c in raw.items():
            kinds[g[1:]] += 1
            total[g[1:]] += c
        levels.append(Counter({g: total[g] if k > 1 and g[0] == "\0" else kinds[g] for g in kinds}))
        raw = total
    levels = levels[::-1]

    def p(gram, floor):
        value = floor
        for k, level in enumerate(levels, 1):
            own, context = gram[-k:], gram[-k:-1]
            of = [c for g, c in level.items() if g[:-1] == context]
            if not of:
                continue
            ones, twos = sum(c == 1 for c in level.values()), sum(c == 2 for c in level.values())
            d = min(max(ones / (ones + 2 * twos) if ones else 0.5, 0.1), 0.95)
            value = max(level[own] - d, 0) / sum(of) + d * len(of) / sum(of) * value if own in level else d * len(of) / sum(of) * value
        return value

    return p


def test_model_equals_plain_dictionaries(spark):
    learn = {"a": ["the cat, The hat! x1y2 sat", "on a mat"], "b": ["der Hut über Öl", "die Katze saß"]}
    docs = spark.createDataFrame([(t, lang) for lang, ts in learn.items() for t in ts], "text string, lang string")
    model = langid.fit(docs)
    for text in ("the hut", "saß on öl", "zzz q", "cat9 hat"):
        code, length, _ = langid.symbols([text])
        bits = model.bits(langid.contexts(code))
        for i, lang in enumerate(model.languages):
            p = kneser_ney(learn[lang])
            expected = []
            for w in words(text):
                padded = "\0" * (langid.ORDER - 1) + w + "\0"
                expected += [-math.log2(p(padded[j - langid.ORDER + 1 : j + 1], model.floor)) for j in range(langid.ORDER - 1, len(padded))]
            assert np.allclose(bits[:, i], expected), (text, lang)


def test_probabilities_sum_to_one(spark):
    docs = spark.createDataFrame([("abab abba baab", "x")], "text string, lang string")
    model = langid.fit(docs)
    for context in ([0, 0, 0], [97, 0, 0], [98, 97, 0], [122, 122, 122]):
        parts = [np.array([0, 97, 98, 99], np.uint64)] + [np.full(4, c, np.uint64) for c in context]
        assert abs(np.exp2(-model.bits(parts)[:, 0]).sum() - 1) < 1e-9


def test_odd_rows(spark, odd_docs):
    got = langid.predict(odd_docs).collect()
    assert len(got) == odd_docs.count()
    texts = {r["doc_id"]: r["text"] for r in odd_docs.collect()}
    for r in got:
        text = texts[r["doc_id"]] if r["doc_id"] is not None else None
        if r["doc_id"] is not None:
            assert (r["lang_pred"] == "und") == (not any(c.isalpha() for c in text or ""))
        assert 0 <= r["score"] <= 1
    empty = spark.createDataFrame([], "doc_id long, text string, lang string, score int")
    assert langid.predict(empty).count() == 0 and langid.keep_known(empty).count() == 0
    alone = spark.createDataFrame([(1, "abc", None)], "doc_id long, text string, lang string")
    assert langid.predict(alone).first()["lang_pred"] == "und"


def test_foreign_text_is_rejected_and_columns_stay(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").withColumn("score", F.lit(1))
    alien = spark.createDataFrame([(-1, "Съешь же ещё этих мягких французских булок да выпей чаю " * 5, None, "s", 1, 1), (-2, None, None, "s", 1, 1)], docs.schema)
    kept = langid.keep_known(docs.unionByName(alien))
    assert kept.columns == docs.columns
    assert kept.where("doc_id < 0").count() == 0 and kept.count() >= 0.99 * docs.count()


def test_rare_grams_stay_in_a_large_corpus(spark):
    """1.2 million symbols in one of two languages: once all grams with 3 or fewer occurrences were dropped."""
    learn = {"a": ["the " * 300_000, "cat hat sat"], "b": ["der hut der hut", "katze"]}
    docs = spark.createDataFrame([(t, lang) for lang, ts in learn.items() for t in ts], "text string, lang string")
    model = langid.fit(docs)
    for text in ("cat hat", "katze", "the sat"):
        code, _, _ = langid.symbols([text])
        bits = model.bits(langid.contexts(code))
        for i, lang in enumerate(model.languages):
            p = kneser_ney(learn[lang])
            expected = []
            for w in words(text):
                padded = "\0" * (langid.ORDER - 1) + w + "\0"
                expected += [-math.log2(p(padded[j - langid.ORDER + 1 : j + 1], model.floor)) for j in range(langid.ORDER - 1, len(padded))]
            assert np.allclose(bits[:, i], expected), (text, lang)
