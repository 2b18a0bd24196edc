"""Near-duplicates by consistent weighted sampling over TF-IDF shingles.

Texts are in lower case; words are runs of letters, digits and all characters
outside ASCII. A text is the weighted set of its shingles of five words (one
shingle of all words if it has fewer). A shingle's weight is

    (1 + ln tf) * (1 + ln((1 + N) / (1 + df)) / ln(1 + N)) ** DAMPING,

with N texts and df of them having the shingle. The damping keeps a large group
of near copies together: each copy makes what they share more frequent, and
would else make the few shingles that differ outweigh it. Document frequencies are counted
over all texts in ``DF_BUCKETS`` hashed counters, less the load that other
shingles put on a counter on average; the table is bounded and equal for all.
Two texts are near-duplicates if the weighted Jaccard similarity of their sets,
computed in full, is ``similarity`` or more.

Candidates: improved consistent weighted sampling draws ``BANDS * ROWS`` samples
of each text; a bucket is a band with equal samples, and all pairs of a bucket are
candidates. Texts with the same words are one text here. What is compared is less
than that, and no link is lost:

* In a bucket the text that shares most buckets with others is compared with every
  other text. Links give components, and pairs of one component need no comparison.
* Of what is left, the texts outside a bucket's largest component are queries
  against all its texts, in tiles of bounded size. A tile's texts are read once and
  its pairs leave one link for each query and other component at most.
* A bucket with more than ``wide`` queries is first met by further leaders, as long as
  that links a tenth of its queries; then its texts meet by the rarest shingles of
  each, up to the share of its weight that two near-duplicates can not both lack.
  So texts that only share a frequent passage part.

Classes are the components of all links.

Defined results: null counts as empty; a text without words is a class of its
own; a class's id is its least document id, of equal ids one row stays; a null
id is the least; repeated rows are one class; an empty table gives an empty
table; all other columns are ignored, or kept by :func:`drop_near`.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import groupby, pairwise

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..components import components
from ..joins import key_join, small
from ..scratch import materialise
from . import arrow, kernel, losers

WIDTH = 5
SIMILARITY = 0.8
#: A pair of similarity s meets in a bucket with probability 1 - (1 - s**ROWS) ** BANDS: 0.999 at 0.8.
BANDS, ROWS = 10, 3
DF_BUCKETS = 1 << 18
DAMPING = 0.25
#: Allowed for sums of weights in another order.
SLACK = 1e-9
#: Texts, and shingles, of one side of a tile on average.
TILE, TILE_SHINGLES = 256, 1 << 17
#: Queries of a bucket from which on it is parted by rare shingles, and its leaders in a further round.
WIDE, LEADERS = 20_000, 16
#: Share of the queries of wide buckets that a round of leaders must link for another one.
LEAST_GAIN = 0.1


def _weights_of(hashes: np.ndarray, times: np.ndarray, idf: np.ndarray) -> np.ndarray:
    return (1 + np.log(times)) * idf[(hashes >> np.uint64(40)).astype(np.int64) & (len(idf) - 1)]


def weighted_sets(column: pa.Array, idf: np.ndarray | None, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles and weights end to end, their number by text, and two sums over each text's words in order."""
    data, offsets = arrow.text_buffers(column)
    starts, ends, per_row = kernel.words(data, offsets, kernel.NOT_WORD)
    hashes = kernel.word_hashes(data, starts, ends)
    found, counts = kernel.shingles(hashes, per_row, width)
    distinct, times, kinds = kernel.distinct(found, counts)
    weight = times.astype(np.float64) if idf is None else _weights_of(distinct, times, idf)
    place = np.arange(len(hashes)) - np.repeat(np.cumsum(per_row) - per_row, per_row)
    longest = int(per_row.max(initial=0))
    prints = []
    for base in (kernel.BASE, kernel.STEP):
        part = np.concatenate([[np.uint64(0)], np.cumsum(kernel.mix(hashes ^ np.uint64(base)) * kernel.powers(base, longest + 1)[place], dtype=np.uint64)])
        edge = np.concatenate([[0], np.cumsum(per_row)])
        prints.append((part[edge[1:]] - part[edge[:-1]]).astype(np.int64))
    return distinct, weight, kinds, prints[0], prints[1]


@lru_cache(maxsize=1)
def tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Quantiles, by 16 bits, of Gamma(2, 1), of its logarithm and of the uniform distribution."""
    u = (np.arange(1 << 16) + 0.5) / (1 << 16)
    x = np.linspace(0, 40, 2_000_001)
    gamma = np.interp(u, 1 - (1 + x) * np.exp(-x), x)
    return gamma, np.log(gamma), u


def multipliers(n: int) -> np.ndarray:
    return kernel.mix(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(kernel.STEP)) | np.uint64(1)


def band_keys(hashes: np.ndarray, weights: np.ndarray, counts: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """Key of each band of each text that has shingles: texts by bands."""
    has = counts > 0
    size = counts[has]
    starts = np.cumsum(size) - size
    out = np.zeros((len(size), bands), dtype=np.uint64)
    if not len(size):
        return out
    gamma, log_gamma, uniform = tables()
    log_weight = np.log(weights)
    low = np.uint64(0xFFFF)
    for k, factor in enumerate(multipliers(bands * rows)):
        h = hashes * factor
        r = gamma[(h >> np.uint64(48)).astype(np.int64)]
        b = uniform[((h >> np.uint64(32)) & low).astype(np.int64)]
        t = np.floor(log_weight / r + b)
        a = log_gamma[((h >> np.uint64(16)) & low).astype(np.int64)] - r * (t - b + 1)
        least = np.minimum.reduceat(a, starts)
        hit = np.flatnonzero(a == np.repeat(least, size))
        at = hit[np.searchsorted(hit, starts)]
        sample = kernel.mix(h[at] ^ kernel.mix(t[at].astype(np.int64).astype(np.uint64)))
        out[:, k // rows] = kernel.mix(out[:, k // rows] * np.uint64(kernel.BASE) + sample)
    return out


def document_frequencies(docs: DataFrame, *, text_col: str = "text", width: int = WIDTH, buckets: int = DF_BUCKETS) -> np.ndarray:
    """IDF of every counter, over all texts; ``buckets`` rows and one reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, texts = np.zeros(buckets, dtype=np.int64), 0
        for _, column in arrow.text_chunks(batches, "text"):
            hashes, _, kinds, _, _ = weighted_sets(column, None, width)
            total += np.bincount((hashes >> np.uint64(40)).astype(np.int64) & (buckets - 1), minlength=buckets)
            texts += int((kinds > 0).sum())
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(total[at], texts))], names=["bucket", "n"])

    lowered = docs.select(F.lower(F.col(text_col).cast("string")).alias("text"))
    summed = lowered.mapInArrow(run, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    total = np.zeros(buckets)
    own = summed[summed["bucket"] >= 0]
    total[own["bucket"].to_numpy()] = own["n"].to_numpy()
    texts = max(1, int(summed.loc[summed["bucket"] == -1, "n"].sum()))
    df = np.maximum(1.0, total - (total.sum() - total) / (buckets - 1))
    return (1 + np.log((1 + texts) / (1 + np.minimum(df, texts))) / np.log(1 + texts)) ** DAMPING


def signatures(docs: DataFrame, idf: Broadcast, *, id_col: str, text_col: str, width: int, bands: int, rows: int) -> DataFrame:
    """Of every row: two hashes of its words, the number of its shingles, the sum of their weights and its band keys."""
    schema = T.StructType(
        [
            T.StructField("doc_id", docs.schema[id_col].dataType),
            *(T.StructField(x, T.LongType()) for x in ("key", "f1", "f2", "n")),
            T.StructField("total", T.DoubleType()),
            T.StructField("bands", T.ArrayType(T.LongType(), False)),
        ]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, column in arrow.text_chunks(batches, "text"):
            hashes, weights, kinds, f1, f2 = weighted_sets(column, idf.value, width)
            keys = band_keys(hashes, weights, kinds, bands, rows).astype(np.int64)
            has = kinds > 0
            flat = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(has * bands)]).astype(np.int32)), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([part.column("id"), part.column("key"), pa.array(f1), pa.array(f2), pa.array(kinds.astype(np.int64)), pa.array(_sums(weights, kinds)), flat], names=schema.names)

    own = docs.select(F.col(id_col).alias("id"), losers.content_key(text_col).alias("key"), F.lower(F.col(text_col).cast("string")).alias("text"))
    return own.mapInArrow(run, schema)


def _sums(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sum of each row's values, always in the same order."""
    return np.bincount(np.repeat(np.arange(len(counts)), counts), weights=values, minlength=len(counts)).astype(np.float64)


def similarities(a: pa.Array, b: pa.Array, idf: np.ndarray, width: int) -> np.ndarray:
    """Weighted Jaccard similarity of the texts in the same place."""
    left, right = weighted_sets(a, idf, width), weighted_sets(b, idf, width)
    pair = np.concatenate([np.repeat(np.arange(len(x[2])), x[2]) for x in (left, right)])
    hashes, weight = np.concatenate([left[0], right[0]]), np.concatenate([left[1], right[1]])
    order = np.lexsort((hashes, pair))
    p, h, w = pair[order], hashes[order], weight[order]
    both = np.flatnonzero((p[1:] == p[:-1]) & (h[1:] == h[:-1]))
    shared = np.bincount(p[both], weights=np.minimum(w[both], w[both + 1]), minlength=len(a))
    total = np.bincount(pair, weights=weight, minlength=len(a)) - shared
    return np.divide(shared, total, out=np.zeros(len(a)), where=total > 0)


def verified(pairs: DataFrame, texts: DataFrame, idf: Broadcast, *, similarity: float, width: int) -> DataFrame:
    """The pairs ``(a, b)`` with their similarity where it is enough. A leader's text goes out once a task, not once a pair."""
    met = pairs.join(texts.select(F.col("v").alias("b"), F.col("text").alias("text_b")), "b")
    met = met.join(texts.select(F.col("v").alias("a"), F.col("text").alias("text_a")), "a")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, column in arrow.text_chunks(batches, "text_b", arrow.SLICE_BYTES // 4):
            # Leaders may be longer than members, so the other text bounds slices too.
            for own in arrow.slices(part, "text_a", arrow.SLICE_BYTES // 2):
                s = similarities(own.column("text_a"), own.column("text_b"), idf.value, width)
                near = np.flatnonzero(s >= similarity - SLACK)
                yield pa.RecordBatch.from_arrays([own.column("a").take(near), own.column("b").take(near), pa.array(s[near])], names=["a", "b", "similarity"])

    return met.select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long, similarity double")


def classes(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    similarity: float = SIMILARITY,
    width: int = WIDTH,
    bands: int = BANDS,
    rows: int = ROWS,
    tile: int = TILE,
    wide: int = WIDE,
) -> DataFrame:
    """One row per document: its class, the class's size, and whether it is the one that stays."""
    spark = docs.sparkSession
    idf = spark.sparkContext.broadcast(document_frequencies(docs, text_col=text_col, width=width))
    signed = signatures(docs, idf, id_col=id_col, text_col=text_col, width=width, bands=bands, rows=rows)
    signed = materialise(signed.withColumn("row_id", F.monotonically_increasing_id()), "near-signatures")
    # Texts with the same words are one text from here on, known by its first row.
    alike = signed.where("n > 0").groupBy("f1", "f2").agg(F.min(F.struct("doc_id", "row_id", "key", "n", "total", "bands")).alias("first"))
    texts = materialise(alike.select("f1", "f2", F.col("first.row_id").alias("v"), *[f"first.{x}" for x in ("doc_id", "key", "n", "total", "bands")]), "near-texts")
    entries = texts.select("v", "n", "total", F.posexplode("bands").alias("band", "bucket"))
    sizes = entries.groupBy("band", "bucket").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    shared = materialise(entries.join(sizes, ["band", "bucket"]), "near-shared")
    central = shared.groupBy("v").agg(F.sum("size").alias("central"))
    shared = materialise(shared.drop("size").join(central, "v"), "near-buckets")
    wanted = materialise(texts.join(shared.select("v").distinct(), "v").select("v", "doc_id", "key"), "near-wanted")
    bodies = docs.select(F.col(id_col).alias("__id"), losers.content_key(text_col).alias("__key"), F.lower(F.col(text_col).cast("string")).alias("text"))
    bodies = key_join(bodies, wanted, bodies["__id"].eqNullSafe(wanted["doc_id"]) & (bodies["__key"] == wanted["key"]), "inner")
    bodies = materialise(bodies.select("v", "text"), "near-bodies")
    if not small(wanted.where("doc_id is null"), 0) or bodies.count() > wanted.count():
        bodies = materialise(bodies.dropDuplicates(["v"]), "near-bodies")
    return _result(signed, texts, _linked(shared, bodies, idf, similarity=similarity, width=width, tile=tile, wide=wide))


def _linked(shared: DataFrame, bodies: DataFrame, idf: Broadcast, *, similarity: float, width: int, tile: int, wide: int) -> DataFrame:
    """``(v, c)`` of the texts that have a link."""
    options = {"similarity": similarity, "width": width}
    most = F.max(F.struct("central", (-F.col("v")).alias("back"), "total"))
    heads = shared.groupBy("band", "bucket").agg(most.alias("head"))
    heads = materialise(heads.select("band", "bucket", (-F.col("head.back")).alias("head"), F.col("head.total").alias("head_total")), "near-heads")
    met = shared.join(heads, ["band", "bucket"]).where("v <> head")
    # No pair is more similar than the lesser of the two sums of weights is to the greater.
    close = F.least("total", "head_total") >= F.greatest("total", "head_total") * (similarity - SLACK)
    pairs = materialise(met.where(close).select(F.least("head", "v").alias("a"), F.greatest("head", "v").alias("b")).distinct(), "near-pairs")
    known = materialise(components(verified(pairs, bodies, idf, **options)), "near-known")
    # Leaders have met their whole bucket and are done with it.
    rest = met.select("band", "bucket", "v", "n", "central").join(known, "v", "left").withColumn("c", F.coalesce("c", "v"))
    rest = materialise(rest, "near-rest")
    several = _several(rest, tile)
    gain = 1.0
    while gain >= LEAST_GAIN and not (broad := several.where(F.col("queries") > wide)).isEmpty():
        heads = materialise(_leaders(rest, broad), "near-heads")
        found = materialise(_tile_links(_tiles(_led(rest, broad, heads), bodies), idf, **options), "near-links")
        met = rest.join(heads.select("band", "bucket", "v"), ["band", "bucket", "v"], "left_anti")
        known, rest = _joined(known, met, found)
        several = _several(rest, tile)
        gain = found.select("b").distinct().count() / broad.agg(F.sum("queries").alias("n")).first()["n"]
    if not (broad := several.where(F.col("queries") > wide)).isEmpty():
        parted = _by_prefixes(rest.join(broad, ["band", "bucket"], "left_semi"), bodies, idf, **options)
        rest = materialise(rest.join(broad, ["band", "bucket"], "left_anti").select(*parted.columns).unionByName(parted), "near-parted")
        several = _several(rest, tile)
    if several.isEmpty():
        return known
    found = materialise(_tile_links(_tiles(_placed(rest, several), bodies), idf, **options), "near-links")
    return _joined(known, rest, found)[0]


def _several(rest: DataFrame, tile: int) -> DataFrame:
    """Buckets of several components: the largest component, the texts outside it, and tiles along either side."""
    of = rest.groupBy("band", "bucket", "c").agg(F.count(F.lit(1)).alias("n"), F.sum("n").alias("shingles"))
    of = of.groupBy("band", "bucket").agg(F.max(F.struct("n", "c", "shingles")).alias("top"), F.sum("n").alias("n"), F.sum("shingles").alias("shingles"), F.count(F.lit(1)).alias("kinds"))

    def along(n: Column, shingles: Column) -> Column:
        return F.greatest(F.ceil(n / tile), F.ceil(shingles / TILE_SHINGLES)).cast("int")

    queries, wordy = F.col("n") - F.col("top.n"), F.col("shingles") - F.col("top.shingles")
    found = of.where("kinds > 1").select("band", "bucket", F.col("top.c").alias("top"), queries.alias("queries"), along(F.col("n"), F.col("shingles")).alias("across"), along(queries, wordy).alias("down"))
    return materialise(found, "near-several")


def _side(tiles: str, salt: int) -> Column:
    return F.pmod(F.xxhash64("v", F.lit(salt)), F.col(tiles)).cast("int")


def _placed(rest: DataFrame, several: DataFrame) -> DataFrame:
    """Every text of an open bucket in a tile of each row of tiles, and every query in a tile of each column too."""
    met = key_join(rest, several, ["band", "bucket"], "inner")
    met = met.withColumns({"x": _side("across", 1), "y": F.when(F.col("c") != F.col("top"), _side("down", 2))})
    members = met.withColumn("row", F.explode(F.sequence(F.lit(0), F.col("down") - 1)))
    members = members.select("band", "bucket", F.col("x").alias("column"), "row", "v", "c", F.lit(True).alias("member"), F.coalesce(F.col("y") == F.col("row"), F.lit(False)).alias("query"))
    others = met.where("y is not null").withColumn("column", F.explode(F.sequence(F.lit(0), F.col("across") - 1))).where("column <> x")
    return members.unionByName(others.select("band", "bucket", "column", F.col("y").alias("row"), "v", "c", F.lit(False).alias("member"), F.lit(True).alias("query")))


def _leaders(rest: DataFrame, broad: DataFrame) -> DataFrame:
    """Of each wide bucket the most central texts of its largest component, in every tile."""
    rank = F.row_number().over(Window.partitionBy("band", "bucket").orderBy(F.desc("central"), "v"))
    first = key_join(rest, broad, ["band", "bucket"], "inner").where("c = top").withColumn("rank", rank).where(F.col("rank") <= LEADERS)
    return first.select("band", "bucket", "v", "c", "across")


def _led(rest: DataFrame, broad: DataFrame, heads: DataFrame) -> DataFrame:
    """Tiles of wide buckets: leaders as queries against the texts outside the largest component."""
    met = key_join(rest, broad, ["band", "bucket"], "inner").where("c <> top")
    members = met.select("band", "bucket", _side("across", 1).alias("column"), F.lit(0).alias("row"), "v", "c", F.lit(True).alias("member"), F.lit(False).alias("query"))
    queries = heads.withColumn("column", F.explode(F.sequence(F.lit(0), F.col("across") - 1)))
    return members.unionByName(queries.select("band", "bucket", "column", F.lit(0).alias("row"), "v", "c", F.lit(False).alias("member"), F.lit(True).alias("query")))


def _tiles(placed: DataFrame, bodies: DataFrame) -> DataFrame:
    """Texts dealt by tile, those of one tile after another."""
    own = placed.withColumn("tile", F.xxhash64("band", "bucket", "column", "row")).select("tile", "v", "c", "member", "query")
    return materialise(own, "near-tiles").join(bodies, "v").repartition("tile").sortWithinPartitions("tile")


def tile_links(
    c: np.ndarray, member: np.ndarray, query: np.ndarray, counts: np.ndarray, hashes: np.ndarray, weights: np.ndarray, similarity: float
) -> tuple[np.ndarray, np.ndarray]:
    """Links of one tile: for each query and each other component one at most, as components."""
    total = _sums(weights, counts)
    rows = np.flatnonzero(member & (counts > 0))
    rows = rows[np.argsort(total[rows], kind="stable")]
    starts = np.cumsum(counts) - counts
    edge = np.concatenate([[0], np.cumsum(counts[rows])])
    # Entries of the members end to end, by the sum of weights, so those a query can be near are one range.
    at = np.repeat(starts[rows] - edge[:-1], counts[rows]) + np.arange(edge[-1])
    words, code = np.unique(hashes, return_inverse=True)
    own_code, own_weight, ranked = code[at], weights[at], total[rows]
    held = np.zeros(len(words))
    out_a, out_b = [], []
    for q in np.flatnonzero(query & (counts > 0)).tolist():
        low = int(np.searchsorted(ranked, total[q] * (similarity - SLACK)))
        high = int(np.searchsorted(ranked, total[q] / (similarity - SLACK), side="right"))
        if low >= high:
            continue
        mine = code[starts[q] : starts[q] + counts[q]]
        held[mine] = weights[starts[q] : starts[q] + counts[q]]
        span = slice(edge[low], edge[high])
        both = np.add.reduceat(np.minimum(held[own_code[span]], own_weight[span]), edge[low:high] - edge[low])
        held[mine] = 0.0
        near = (both >= (similarity - SLACK) * (ranked[low:high] + total[q] - both)) & (c[rows[low:high]] != c[q])
        if near.any():
            others = np.unique(c[rows[low:high][near]])
            out_a.append(np.full(len(others), c[q]))
            out_b.append(others)
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *out_a]), np.concatenate([none, *out_b])


def _tile_links(tiles: DataFrame, idf: Broadcast, *, similarity: float, width: int) -> DataFrame:
    """Pairs of components ``(a, b)`` that a text of each links."""

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for part, column in arrow.text_chunks(batches, "text"):
            tile, c, member, query = (part.column(x).to_numpy(zero_copy_only=False) for x in ("tile", "c", "member", "query"))
            hashes, weights, counts, _, _ = weighted_sets(column, idf.value, width)
            edge = np.concatenate([[0], np.cumsum(counts)])
            cuts = [0, *(np.flatnonzero(tile[1:] != tile[:-1]) + 1).tolist(), len(tile)]
            for lo, hi in pairwise(cuts):
                yield tile[lo], (c[lo:hi], member[lo:hi], query[lo:hi], counts[lo:hi], hashes[edge[lo] : edge[hi]], weights[edge[lo] : edge[hi]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, own in groupby(parts(batches), key=lambda x: x[0]):
            a, b = tile_links(*(np.concatenate(x) for x in zip(*(x[1] for x in own))), similarity)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return tiles.select("tile", "c", "member", "query", "text").mapInArrow(run, "a long, b long")


def _joined(known: DataFrame, rest: DataFrame, found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Labels of all texts with a link, and the open texts, after links between components."""
    new = materialise(components(found).select(F.col("v").alias("c"), F.col("c").alias("now")), "near-merged")
    alone = rest.where("c = v").select("v").distinct().join(known.select("v"), "v", "left_anti").withColumn("c", F.col("v"))
    labels = known.unionByName(alone.join(new.select("c"), "c", "left_semi").select("v", "c"))

    def renamed(rows: DataFrame) -> DataFrame:
        return key_join(rows, new, ["c"], "left").withColumn("c", F.coalesce("now", "c")).drop("now").select(*rows.columns)

    return materialise(renamed(labels), "near-known"), materialise(renamed(rest), "near-rest")


def prefixes(column: pa.Array, idf: np.ndarray, *, similarity: float, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each text's rarest shingles end to end, their number and the sum of all weights by text.

    What follows a prefix weighs less than ``similarity`` of its text, so two texts
    of that similarity share a shingle of both prefixes: all have one order, and
    what they share weighs at least that part of either.
    """
    hashes, weights, counts, _, _ = weighted_sets(column, idf, width)
    text = np.repeat(np.arange(len(counts)), counts)
    order = np.lexsort((hashes, -_weights_of(hashes, np.ones(len(hashes)), idf), text))
    total = _sums(weights, counts)
    run = np.concatenate([[0.0], np.cumsum(weights[order])])
    starts = np.cumsum(counts) - counts
    before = run[:-1] - np.repeat(run[starts], counts)
    inside = total[text] - before >= (similarity - SLACK) * total[text]
    return hashes[order][inside], np.bincount(text[inside], minlength=len(counts)), total


def _by_prefixes(left: DataFrame, bodies: DataFrame, idf: Broadcast, *, similarity: float, width: int) -> DataFrame:
    """Texts in a bucket for each shingle of their prefixes that texts of several components have."""
    still = left.select("v", "n", "c").distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, column in arrow.text_chunks(batches, "text"):
            found, counts, _ = prefixes(column, idf.value, similarity=similarity, width=width)
            flat = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(found.astype(np.int64)))
            yield pa.RecordBatch.from_arrays([*(part.column(x) for x in ("v", "n", "c")), flat], names=["v", "n", "c", "rare"])

    own = still.join(bodies, "v").select("v", "n", "c", "text").mapInArrow(run, "v long, n long, c long, rare array<long>")
    entries = materialise(own.select(F.lit(-1).alias("band"), F.explode("rare").alias("bucket"), "v", "n", "c"), "near-prefixes")
    several = entries.groupBy("band", "bucket").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("band", "bucket")
    return entries.join(several, ["band", "bucket"], "left_semi")


def _result(signed: DataFrame, texts: DataFrame, known: DataFrame) -> DataFrame:
    of_text = texts.select("f1", "f2", "v", "doc_id").join(known, "v", "left").withColumn("c", F.coalesce("c", "v"))
    heads = of_text.groupBy("c").agg(F.min(F.struct("doc_id", "v")).alias("head"))
    of_text = materialise(of_text.select("f1", "f2", "c").join(heads, "c").select("f1", "f2", F.col("head.doc_id").alias("class_id"), F.col("head.v").alias("class_row")), "near-classes")
    rows = signed.select("doc_id", "key", "row_id", "n", "f1", "f2")
    with_words = rows.where("n > 0").join(of_text, ["f1", "f2"])
    without = rows.where("n = 0").withColumns({"class_id": F.col("doc_id"), "class_row": F.col("row_id")})
    every = with_words.select(*(names := ("doc_id", "key", "row_id", "class_id", "class_row"))).unionByName(without.select(*names))
    every = materialise(every, "near-rows")
    sizes = materialise(every.groupBy("class_row").agg(F.count(F.lit(1)).alias("class_size")), "near-sizes")
    return every.join(sizes, "class_row").select("doc_id", "class_id", "class_size", (F.col("row_id") == F.col("class_row")).alias("kept"), "key")


def drop_near(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The documents with one of each class, with all their columns."""
    verdicts = classes(docs, id_col=id_col, text_col=text_col, **options).where("class_size > 1").select("doc_id", "key", "kept")
    return losers.drop(docs, verdicts, id_col=id_col, text_col=text_col)
