import re
from collections import defaultdict

from pyspark.sql import functions as F

from roadweave.llm import exact


def brute(rows):
    groups = defaultdict(list)
    for doc_id, text in rows:
        groups[re.sub("[\x20\x09-\x0d]", "", text or "")].append((-len(text or ""), doc_id is not None, doc_id or 0, doc_id))
    out = []
    for members in groups.values():
        members.sort(key=lambda x: x[:3])
        out += [(m[3], members[0][3], len(members), i == 0) for i, m in enumerate(members)]
    return sorted(out, key=str)


def check(docs, **kw):
    got = exact.exact_groups(docs, **kw).select("doc_id", "keep_id", "group_size", "kept").collect()
    assert sorted((tuple(r) for r in got), key=str) == brute([(r["doc_id"], r["text"]) for r in docs.collect()])


def test_against_brute_force(odd_docs, sample):
    check(odd_docs)
    check(sample)


def test_hash_collisions_are_split_by_bytes(odd_docs):
    check(odd_docs, hashed=lambda norm: F.unhex(F.md5(F.substring(norm, 1, 1))))


def test_copies_go_and_all_columns_stay(odd_docs, spark):
    kept = exact.drop_copies(odd_docs.withColumn("h", F.lit(1)))
    assert kept.columns == [*odd_docs.columns, "h"]
    assert kept.count() == exact.exact_groups(odd_docs).where("kept").count()
    norm = F.translate(F.coalesce("text", F.lit("")), exact.WHITE, "")
    assert kept.select(norm).distinct().count() == kept.count()


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, h string, kept int")
    assert exact.exact_groups(docs).count() == 0 and exact.drop_copies(docs).count() == 0
