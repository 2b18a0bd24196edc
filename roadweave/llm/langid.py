"""Language identification by interpolated Kneser-Ney character models.

Every training document is counted: character grams of ``ORDER`` symbols inside
words, letters in lower case, with the word's edges as a symbol. Spark sums the
counts, derives the continuation counts of the shorter orders from all of them, and
the discounts from the numbers of grams seen once and twice; nothing is left out, so
the model grows with the distinct grams of the input. It is a table in the shared
folder: the driver sees the discounts alone, and a worker reads the table once. There,
each language and order is two arrays of sorted 64-bit hashes, of grams with their
discounted probability and of contexts with their interpolation weight. A text
goes to the language of least cross-entropy per symbol.

Rejection is calibrated on the counts of all training documents: a text is
rejected if its cross-entropy lies further than the share ``FAR`` of the way from
the language's own mean to the least mean that another language's text has under
its model, plus ``Z`` standard errors for the text's length.

Defined results: ``und`` with score 0 for null texts and texts without a
letter, which are also rejected; a text whose only letters stand in codes with
digits goes to the first language and is rejected; ``und`` everywhere if nothing can be learned;
rows with a null language or id teach nothing; ties go to the first language in
alphabetical order; repeated rows are judged each; an empty table gives an empty
table; clashing columns are no trouble, as results travel under names that no column has.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyarrow import fs, parquet
from pyspark.sql import DataFrame, functions as F, types as T

from ..scratch import materialise, new_path
from . import arrow, losers

ORDER = 4
#: Standard errors that rejection allows for a text's length.
Z = 4.0
#: How far the cut of rejection lies from a language's own mean to the other's.
FAR = 0.75
MEMO_GRAMS = 400_000
#: Code of all digits, which no letter has.
DIGIT = 1
UNKNOWN = "und"
_FACTORS = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5)


@lru_cache(maxsize=1)
def folding() -> np.ndarray:
    """Lower-case letter of every code point; ``DIGIT`` for digits and 0 for all else."""
    table = np.zeros(0x110000, dtype=np.uint32)
    for i in range(0x110000):
        c = chr(i)
        if c.isalpha():
            table[i] = ord(c.lower()[0])
        elif c.isdigit():
            table[i] = DIGIT
    return table


def symbols(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Folded letters of all texts with one 0 after every word, symbols by text, letters by text.

    Runs of letters and digits that have a digit are keys and codes, not words, and are left out.
    """
    joined = "\n".join(texts) + "\n"
    code = folding()[np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    some = code != 0
    letter = some & (code != DIGIT)
    ends = np.cumsum([len(t) + 1 for t in texts])
    letters = np.concatenate([[0], np.cumsum(letter)[ends - 1]])
    digits = np.flatnonzero(code == DIGIT)
    if len(digits):
        opens = np.flatnonzero(some & ~np.concatenate([[False], some[:-1]]))
        closes = np.flatnonzero(some & ~np.concatenate([some[1:], [False]])) + 1
        runs = np.unique(np.searchsorted(opens, digits, side="right") - 1)
        edge = np.zeros(len(code) + 1, dtype=np.int8)
        edge[opens[runs]] += 1
        edge[closes[runs]] -= 1
        code = np.where(np.cumsum(edge[:-1]) > 0, np.uint32(0), code)
        letter = code != 0
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    before = np.concatenate([[0], np.cumsum(keep)[ends - 1]])
    return code[keep].astype(np.uint64), np.diff(before), np.diff(letters)


def contexts(code: np.ndarray) -> list[np.ndarray]:
    """The symbol at each place and those before it in its word; 0 beyond the word's start."""
    out = [code]
    for j in range(1, ORDER):
        back = np.zeros_like(code)
        back[j:] = code[:-j]
        if j > 1:
            back[out[-1] == 0] = 0
        out.append(back)
    return out


def gram_hash(parts: list[np.ndarray]) -> np.ndarray:
    """Hash of grams given by their symbols, the last symbol first."""
    h = np.zeros(len(parts[0]), dtype=np.uint64)
    for part, factor in zip(parts, _FACTORS):
        h += (part + np.uint64(1)) * np.uint64(factor)
    return h


class Order:
    """Sorted hash arrays of one order of one language."""

    def __init__(self, grams: list[np.ndarray], counts: np.ndarray, discount: float):
        context = gram_hash(grams[1:]) if len(grams) > 1 else np.zeros(len(counts), np.uint64)
        self.contexts, inverse = np.unique(context, return_inverse=True)
        total = np.bincount(inverse, weights=counts)
        kinds = np.bincount(inverse)
        self.weight = discount * kinds / total
        h = gram_hash(grams)
        order = np.argsort(h)
        self.grams = h[order]
        self.value = ((counts - discount) / total[inverse])[order]

    def mix(self, gram: np.ndarray, context: np.ndarray, lower: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.contexts, context), len(self.contexts) - 1)
        known = self.contexts[at] == context
        weight = np.where(known, self.weight[at], 1.0)
        at = np.minimum(np.searchsorted(self.grams, gram), len(self.grams) - 1)
        return np.where(known & (self.grams[at] == gram), self.value[at], 0.0) + weight * lower


_MASK = (1 << 21) - 1


def unpacked(near: np.ndarray, far: np.ndarray) -> list[np.ndarray]:
    """Symbols of packed grams, the last one first."""
    near = near.astype(np.uint64)
    return [near & np.uint64(_MASK), near >> np.uint64(21) & np.uint64(_MASK), near >> np.uint64(42), far.astype(np.uint64)]


@lru_cache(maxsize=1)
def _orders(path: str, discounts: tuple[tuple[tuple[str, int], float], ...]) -> list[list[Order]]:
    """Of each language of a stored model its orders, the shortest first; a process keeps those it read last."""
    system, root = fs.FileSystem.from_uri(path)
    table = parquet.read_table(root, filesystem=system)
    lang, order = table.column("lang").to_numpy(zero_copy_only=False), table.column("order").to_numpy()
    near, far, value = (table.column(x).to_numpy() for x in ("near", "far", "value"))
    out: dict[str, list[Order]] = {}
    for (name, k), discount in discounts:
        at = np.flatnonzero((order == k) & (lang == name))
        out.setdefault(name, []).append(Order(unpacked(near[at], far[at])[:k], value[at].astype(np.float64), discount))
    return [out[name] for name in sorted(out)]


class Model:
    """Models of all languages: a table of counts by order, which is read where it is first needed, and discounts."""

    def __init__(self, path: str, discounts: dict[tuple[str, int], float], floor: float):
        self.path, self.discounts, self.floor = path, discounts, floor
        self.languages = sorted({lang for lang, _ in discounts})
        self.cut = self.sd = np.zeros(0)

    @property
    def orders(self) -> list[list[Order]]:
        return _orders(self.path, tuple(sorted(self.discounts.items())))

    def bits(self, parts: list[np.ndarray]) -> np.ndarray:
        """Bits of each gram's last symbol under each language: grams by languages."""
        out = np.empty((len(parts[0]), len(self.languages)))
        grams = [gram_hash(parts[: k + 1]) for k in range(ORDER)]
        context = [np.zeros(len(parts[0]), np.uint64)] + [gram_hash(parts[1 : k + 1]) for k in range(1, ORDER)]
        for i, orders in enumerate(self.orders):
            p = np.full(len(parts[0]), self.floor)
            for k, order in enumerate(orders):
                p = order.mix(grams[k], context[k], p)
            out[:, i] = -np.log2(p)
        return out

    def calibrate(self, rows: dict[str, tuple]) -> None:
        """Cuts of rejection from each language's number of grams, sums of bits under each model and of its own squared bits."""
        size = len(self.languages)
        mean, self.sd = np.zeros((size, size)), np.zeros(size)
        for j, lang in enumerate(self.languages):
            n, bits, squares = rows[lang]
            mean[j] = np.array(bits) / n
            self.sd[j] = np.sqrt(max(0.0, squares / n - mean[j, j] ** 2))
        own = mean.diagonal()
        # Without a second language the uniform distribution stands in for it.
        other = np.array([min([mean[j, i] for j in range(size) if j != i], default=-np.log2(self.floor)) for i in range(size)])
        self.cut = np.maximum(own, own + FAR * (other - own))

    def beyond(self, best: np.ndarray, entropy: np.ndarray, length: np.ndarray) -> np.ndarray:
        return entropy > self.cut[best] + Z * self.sd[best] / np.sqrt(np.maximum(length, 1))


class Scorer:
    """Scores texts slice by slice and remembers the grams it has met."""

    def __init__(self, model: Model):
        self.model = model
        self.clear()

    def clear(self) -> None:
        self.known = np.zeros(0, np.uint64)
        self.bits = np.zeros((0, len(self.model.languages)))

    def _bits(self, grams: np.ndarray, parts: list[np.ndarray]) -> np.ndarray:
        at = np.searchsorted(self.known, grams)
        new = np.ones(len(grams), dtype=bool) if not len(self.known) else self.known[np.minimum(at, len(self.known) - 1)] != grams
        if new.any():
            if len(self.known) > MEMO_GRAMS:
                self.clear()
                new[:] = True
            known = np.concatenate([self.known, grams[new]])
            bits = np.concatenate([self.bits, self.model.bits([p[new] for p in parts])])
            order = np.argsort(known)
            self.known, self.bits = known[order], bits[order]
            at = np.searchsorted(self.known, grams)
        return self.bits[at]

    def __call__(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Language, score, bits per symbol and rejection of each text."""
        n = len(texts)
        names, score, entropy, rejected = [UNKNOWN] * n, np.zeros(n), np.full(n, np.nan), np.ones(n, dtype=bool)
        code, length, letters = symbols(texts)
        has = np.flatnonzero(length)
        if not self.model.languages:
            return names, score, entropy, rejected
        for i in np.flatnonzero((letters > 0) & (length == 0)).tolist():
            names[i], score[i] = self.model.languages[0], 1 / len(self.model.languages)
        if not len(has):
            return names, score, entropy, rejected
        parts = contexts(code)
        inverse, grams = pd.factorize(gram_hash(parts))
        first = np.empty(len(grams), dtype=np.int64)
        first[inverse[::-1]] = np.arange(len(inverse) - 1, -1, -1)
        bits = self._bits(grams, [p[first] for p in parts])
        starts = (np.cumsum(length) - length)[has]
        total = np.add.reduceat(bits[inverse], starts, axis=0) / length[has, None]
        best = total.argmin(axis=1)
        low = total[np.arange(len(has)), best]
        odds = np.exp2(-(total - low[:, None]) * length[has, None])
        score[has] = 1.0 / odds.sum(axis=1)
        entropy[has] = low
        rejected[has] = self.model.beyond(best, low, length[has])
        for i, b in zip(has.tolist(), best.tolist()):
            names[i] = self.model.languages[b]
        return names, score, entropy, rejected


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Gram counts of a task's documents by language."""
    held: list[pd.DataFrame] = []
    rows = 0

    def merged() -> pd.DataFrame:
        return pd.concat(held).groupby(["lang", "near", "far"], as_index=False, sort=False)["n"].sum()

    for part, column in arrow.text_chunks(batches, "text"):
        texts = column.to_pylist()
        langs, lang_of = np.unique(np.array(part.column("lang").to_pylist(), dtype=object).astype(str), return_inverse=True)
        code, length, _ = symbols(texts)
        if not len(code):
            continue
        parts = contexts(code)
        inverse, grams = pd.factorize(gram_hash(parts))
        first = np.empty(len(grams), dtype=np.int64)
        first[inverse[::-1]] = np.arange(len(inverse) - 1, -1, -1)
        key = np.repeat(lang_of, length) * len(grams) + inverse
        n = np.bincount(key, minlength=len(langs) * len(grams))
        at = np.flatnonzero(n)
        which = first[at % len(grams)]
        near = parts[0][which] | parts[1][which] << np.uint64(21) | parts[2][which] << np.uint64(42)
        held.append(pd.DataFrame({"lang": langs[at // len(grams)], "near": near.astype(np.int64), "far": parts[3][which].astype(np.int64), "n": n[at]}))
        rows += len(at)
        if rows > 2_000_000:
            held = [merged()]
            rows = len(held[0])
            if rows > 1_000_000:
                yield pa.RecordBatch.from_pandas(held[0], preserve_index=False)
                held, rows = [], 0
    if held:
        yield pa.RecordBatch.from_pandas(merged(), preserve_index=False)


def _levels(counts: DataFrame) -> DataFrame:
    """Counts of the full order and, of shorter grams, by how many symbols precede them; at a word's start by counts."""
    out = counts.select("lang", F.lit(ORDER).alias("order"), "near", "far", F.col("n").alias("value"))
    raw = counts.select("lang", "near", F.col("n").alias("raw"))
    for k in range(ORDER - 1, 0, -1):
        raw = raw.withColumn("near", F.col("near").bitwiseAND((1 << 21 * k) - 1)).groupBy("lang", "near").agg(F.sum("raw").alias("raw"), F.count(F.lit(1)).alias("kinds"))
        # For k = 1 the leftmost symbol is the one predicted, so only longer grams can begin a word.
        starts = F.shiftright("near", 21 * (k - 1)) == 0 if k > 1 else F.lit(False)
        out = out.unionByName(raw.select("lang", F.lit(k).alias("order"), "near", F.lit(0).cast("long").alias("far"), F.when(starts, F.col("raw")).otherwise(F.col("kinds")).alias("value")))
        raw = raw.drop("kinds")
    return out


def _bits_by_language(counts: DataFrame, model: Model) -> dict[str, tuple]:
    """Over all counted grams: their number, bits under each model and squared bits under their own."""
    names = [f"b{i}" for i in range(len(model.languages))]
    schema = "lang string, n double, squares double, " + ", ".join(f"{x} double" for x in names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lang = batch.column("lang").to_numpy(zero_copy_only=False)
            near, far, n = (batch.column(x).to_numpy() for x in ("near", "far", "n"))
            bits = model.bits(unpacked(near, far))
            for j, name in enumerate(model.languages):
                at = np.flatnonzero(lang == name)
                if len(at):
                    sums = (bits[at] * n[at, None]).sum(axis=0)
                    yield pa.RecordBatch.from_pylist([{"lang": name, "n": float(n[at].sum()), "squares": float((bits[at, j] ** 2 * n[at]).sum()), **dict(zip(names, sums.tolist()))}])

    summed = counts.mapInArrow(run, schema).groupBy("lang").agg(*[F.sum(x).alias(x) for x in ("n", "squares", *names)])
    return {r["lang"]: (r["n"], [r[x] for x in names], r["squares"]) for r in summed.collect()}


def fit(docs: DataFrame, *, text_col: str = "text", lang_col: str = "lang") -> Model:
    """Model of all rows that have a language; every row is counted and every gram kept."""
    spark = docs.sparkSession
    own = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang"))
    counts = own.mapInArrow(_count, "lang string, near long, far long, n long").groupBy("lang", "near", "far").agg(F.sum("n").alias("n"))
    counts = materialise(counts, "lang-grams")
    path = new_path(spark, "lang-model")
    _levels(counts).write.parquet(path)
    levels = spark.read.parquet(path)
    seen = levels.groupBy("lang", "order").agg(F.count_if(F.col("value") == 1).alias("ones"), F.count_if(F.col("value") == 2).alias("twos")).collect()
    discounts = {(r["lang"], r["order"]): min(max(r["ones"] / (r["ones"] + 2 * r["twos"]) if r["ones"] else 0.5, 0.1), 0.95) for r in seen}
    symbols_seen = levels.where("order = 1").agg(F.count_distinct("near")).first()[0]
    model = Model(path, discounts, 1.0 / (symbols_seen + 1))
    if model.languages:
        model.calibrate(_bits_by_language(counts, model))
    return model


RESULTS = ("lang_pred", "lang_score", "lang_bits", "lang_rejected")


def annotate(docs: DataFrame, model: Model, *, text_col: str = "text") -> tuple[DataFrame, list[str]]:
    """``docs`` with language, score, bits per symbol and rejection, and the names of these four: ``RESULTS``, or like them."""
    names = [losers.fresh(docs, n) for n in RESULTS]
    # Plain names on the way through Python, where a name with a dot would be taken for a field.
    plain = docs.toDF(*(f"c{i}" for i in range(len(docs.columns))))
    types = (T.StringType(), T.DoubleType(), T.DoubleType(), T.BooleanType())
    schema = T.StructType([*plain.schema.fields, *(T.StructField(f"r{i}", t) for i, t in enumerate(types))])
    text = f"c{[c.lower() for c in docs.columns].index(text_col.lower())}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for part, column in arrow.text_chunks(batches, text):
            found, score, bits, rejected = scorer([t or "" for t in column.to_pylist()])
            new = [pa.array(found, pa.string()), pa.array(score), pa.array(bits), pa.array(rejected)]
            yield pa.RecordBatch.from_arrays([*part.columns, *new], names=schema.names)

    return plain.mapInArrow(run, schema).toDF(*docs.columns, *names), names


def held_out(id_col: str = "doc_id"):
    """Whether a document only tests: the CRC-32 of its id as text leaves 2 when divided by 4."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def predict(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Learn from the documents that aren't held out and predict all of them from their text alone."""
    model = fit(docs.where(~held_out(id_col) & F.col(id_col).isNotNull()), text_col=text_col, lang_col=lang_col)
    own = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    judged, (lang, score, bits, rejected) = annotate(own, model)
    return judged.select(
        "doc_id",
        held_out("doc_id").alias("held_out"),
        F.col(lang).alias("lang_pred"),
        F.col(score).alias("score"),
        F.col(bits).alias("bits_per_symbol"),
        F.col(rejected).alias("rejected"),
    )


def keep_known(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The documents that aren't rejected, with all their columns; ``lang`` is the predicted language."""
    model = fit(docs.where(~held_out(id_col) & F.col(id_col).isNotNull()), text_col=text_col, lang_col=lang_col)
    judged, (lang, _, _, rejected) = annotate(docs.withColumn(text_col, F.col(text_col).cast("string")), model, text_col=text_col)
    return judged.where(~F.col(rejected)).withColumn(lang_col, F.col(lang)).select(*losers.quoted(docs.columns))
