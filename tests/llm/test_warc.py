from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from roadweave.llm import warc

ODD = [(1, "http://a", "<p>x</p>"), (2, "http://b\r\nX: y", "<p>x</p>"), (3, None, None), (4, "http://c", ""), (5, "http://é", "é\r\n\r\nWARC/1.1 漢字" * 500), (6, "u", "x" * 600_000), (7, "u", "alone"), (7, "u", "alone"), (None, "n", "alone"), (None, None, "own")]


def expected(rows, least=0):
    groups = defaultdict(list)
    for page_id, _, html in rows:
        groups[html or ""].append(page_id)
    out = []
    for html, ids in groups.items():
        known = [i for i in ids if i is not None]
        top = max(known) if known and len(ids) > 1 and len(html.encode()) >= least else None
        for i in ids:
            revisit = top is not None and i != top
            out.append((i, len(html.encode()), warc.base32_sha1(html.encode()), "revisit" if revisit else "response", top if revisit else None))
    return sorted(out, key=str)


def got(df):
    return sorted((tuple(r) for r in df.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()), key=str)


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "page_id long, url string, html string").withColumn("bundle", F.lit("clash"))


def test_round_trip(odd):
    assert got(warc.archive_and_read(odd)) == expected(ODD)
    assert got(warc.archive_and_read(odd, least=6)) == expected(ODD, 6)


def test_whole_pages_table(spark):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    pages = pages.unionByName(pages.withColumn("page_id", F.col("page_id") + 10_000).limit(20))
    assert got(warc.archive_and_read(pages)) == expected([tuple(r) for r in pages.collect()])


def test_random_access_by_the_index(odd, spark):
    index = warc.write(odd)
    assert index.count() == len(ODD)
    html = {i: h for i, _, h in ODD}
    rows = warc.fetch(index.where("page_id in (2, 5, 6)")).collect()
    assert {r["page_id"] for r in rows} == {2, 5, 6}
    assert all(r["payload"] == html[r["page_id"]] for r in rows if r["record_type"] == "response")
    assert warc.read(spark, index, payload=True).where("page_id = 5").first()["payload"] == html[5]


def test_reading_by_the_index(odd, spark):
    index = warc.write(odd)
    assert got(warc.read_indexed(index)) == got(warc.read(spark, index)) == expected(ODD)
    assert warc.read_indexed(index, payload=True).where("page_id = 5").first()["payload"] == ODD[4][2]
    assert warc.read_indexed(index.where("page_id = 6")).count() == 1
    wrong = index.withColumn("record_id", F.concat("record_id", F.lit("x")))
    with pytest.raises(Exception, match="no record"):
        warc.read_indexed(wrong).collect()
    bundles = index.select("bundle").distinct().count()
    assert warc.read_indexed(index).rdd.getNumPartitions() >= bundles


def test_seek_table_is_standard(odd):
    import zstandard
    from pyarrow import fs

    uri = warc.write(odd).first()["bundle"]
    system, path = fs.FileSystem.from_uri(uri)
    data = system.open_input_file(path).read()
    bundle = warc.open_bundle(uri)
    whole = b"".join(bundle.frame(i) for i in range(len(bundle)))
    # A plain decoder reads all frames and skips the table.
    assert zstandard.ZstdDecompressor().stream_reader(data, read_across_frames=True).read() == whole


def test_empty_table(spark):
    assert warc.archive_and_read(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
