import re
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from roadweave.llm import rules

WORD = re.compile("[^\x20\x09-\x0d]+")


def brute(text):
    text = text or ""
    words = WORD.findall(text)
    lines = [x for x in text.split("\n") if WORD.search(x)]
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = Counter(grams)
    covered = {i + j for i, g in enumerate(grams) if often[g] > 1 for j in range(3)}
    runs = sum(a == b for a, b in zip(words, words[1:]))
    return runs, len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered)


def check(docs):
    docs = docs.selectExpr("text as doc_id", "text")
    rows = rules.measure(docs).collect()
    assert len(rows) == docs.count()
    for r in rows:
        assert tuple(r[c] for c in ("n_run_words", *rules.COUNTS[:5])) == brute(r["doc_id"]), r["doc_id"]


def test_counts_against_brute_force(spark, odd_docs, sample):
    check(odd_docs)
    check(sample)
    texts = ["a b c a b c", "a b c d a b c", "x\nx\n \n\ny\nx", "#|a b\x0bc\x0cd", "a a a a", "é é é é\né é é é", "\n\n\n", "a b"]
    check(spark.createDataFrame([(t,) for t in texts], "text string"))


def test_learned_list_separates_the_labels(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    judged = rules.judge(docs, labels).join(labels, "doc_id").where("not base_failed")
    table = {(r["quality"], r["kept"]): r["n"] for r in judged.groupBy("quality", "kept").agg(F.count("*").alias("n")).collect()}
    assert table.get((1, False), 0) <= 0.005 * table[(1, True)]
    assert table[(0, False)] >= 0.9 * (table[(0, False)] + table.get((0, True), 0))


def test_conjunction_is_learned_and_expressed(spark):
    rng = np.random.default_rng(0)
    x = {f: rng.random(3000) for f in rules.FEATURES}
    bad = (x["symbol_share"] > 0.6) & (x["repeat_share"] < 0.5)
    learned = rules.learn(x, bad)
    found = np.any([rules.covers(r, x) for r in learned], axis=0)
    assert (found == bad).mean() > 0.97 and (found & ~bad).sum() <= 0.02 * found.sum()
    frame = spark.createDataFrame([tuple(float(x[f][i]) for f in rules.FEATURES) + (i,) for i in range(300)], [*rules.FEATURES, "i"])
    for r in frame.select("i", rules.expression(learned).alias("k")).collect():
        first = next((k for k, rule in enumerate(learned, 1) if all(x[c.feature][r["i"]] >= c.value if c.at_least else x[c.feature][r["i"]] <= c.value for c in rule)), None)
        assert r["k"] == first


def test_no_labels_and_empty_tables(spark, odd_docs):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    judged = rules.judge(odd_docs, none)
    assert judged.count() == odd_docs.count() and judged.where("rule is not null").count() == 0
    assert judged.where("kept <> (not base_failed)").count() == 0
    empty = spark.createDataFrame([], "doc_id long, text string, n_words int, kept int")
    assert rules.judge(empty, none).count() == 0
