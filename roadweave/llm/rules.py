"""Quality rules as a learned decision list.

Statistics of every text are counted on its bytes. From the statistics of
labelled documents, at most ``SAMPLE`` of them, sequential covering learns an
ordered list of rules that reject: a rule is a conjunction of thresholds, grown
on two thirds of the sample by information gain and pruned on the other third
while that raises its precision; documents it covers leave the sample and the
next rule is grown, until a rule is no longer precise enough. The list becomes
one Spark CASE expression, which names the rule that rejected.

Defined results: a null or empty text has no words, all counts 0, and fails the
base rules; without labels of both classes the list is empty and the base rules
decide; null ids match no label; of several labels of a document the least
counts; repeated rows are judged each; an empty table gives an empty table;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..scratch import materialise
from . import arrow, kernel

#: Labelled documents with distinct statistics that the list is fitted on: those whose hash lies below the share that this
#: is of them all. Twice as many are a bound that no draw reaches.
SAMPLE = 30_000
#: Thresholds of a feature that are tried at most, at quantiles of its values.
THRESHOLDS = 64
#: Least precision of a rule on the pruning part, conditions of a rule, rules of a list, and documents a rule covers at least.
PRECISION, CONDITIONS, RULES, LEAST = 0.95, 4, 12, 4
#: Fixed values of the base rules: words at least, and percent of repeated words at most.
LEAST_WORDS, REPEATED_PERCENT = 50, 50

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters", "n_digits", "n_marks", "n_top_word", "n_capped_words", "n_distinct_words", "n_run_words")
RATIOS = {
    "symbol_share": ("n_symbols", "word_chars"),
    "symbols_per_word": ("n_symbols", "n_words"),
    "dup_line_share": ("n_dup_lines", "n_lines"),
    "repeat_share": ("n_repeat_words", "n_words"),
    "mean_word": ("word_chars", "n_words"),
    "upper_share": ("n_upper", "n_letters"),
    "digit_share": ("n_digits", "word_chars"),
    "mark_share": ("n_marks", "word_chars"),
    "top_word_share": ("n_top_word", "n_words"),
    # Runs of one word tell the same at every length, as the share of distinct words does not.
    "run_share": ("n_run_words", "n_words"),
}
#: What rules may ask for: shares that mean the same at every length and in every language. Length, mean word length and
#: the commonest word's share are measured but left out, as they differ between clean documents too.
FEATURES = tuple(r for r in RATIOS if r not in ("mean_word", "top_word_share"))


def _flags(chars: bytes) -> np.ndarray:
    table = np.zeros(256, dtype=bool)
    table[list(chars)] = True
    return table


_SYMBOLS = _flags(b"#*$%&|<>")
_UPPER = _flags(bytes(range(65, 91)))
_LETTERS = _flags(bytes([*range(65, 91), *range(97, 123)]))
_DIGITS = _flags(bytes(range(48, 58)))
_MARKS = _flags(b"!?")
_NEWLINE = _flags(b"\n")


def statistics(data: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """The counts of every row."""
    n = len(offsets) - 1

    def per_row(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask)])
        return total[offsets[1:]] - total[offsets[:-1]]

    white = kernel.WHITE[data]
    out = {"word_chars": per_row(~white & ((data & 0xC0) != 0x80))}
    for name, table in (("n_symbols", _SYMBOLS), ("n_upper", _UPPER), ("n_letters", _LETTERS), ("n_digits", _DIGITS), ("n_marks", _MARKS)):
        out[name] = per_row(table[data])
    starts, ends, words = kernel.words(data, offsets, kernel.WHITE)
    hashes = kernel.word_hashes(data, starts, ends)
    out["n_words"] = words
    row = np.repeat(np.arange(n), words)
    out["n_capped_words"] = np.bincount(row[_UPPER[data[starts]]], minlength=n)
    again = np.zeros(len(hashes), dtype=bool)
    again[1:] = (hashes[1:] == hashes[:-1]) & (row[1:] == row[:-1])
    out["n_run_words"] = np.bincount(row[again], minlength=n)
    _, times, kinds = kernel.distinct(hashes, words)
    out["n_distinct_words"] = kinds
    out["n_top_word"] = _row_max(times, kinds)
    # A line counts if it has a word; equal lines have equal bytes.
    begin, end, lines = kernel.words(data, offsets, _NEWLINE)
    filled = np.concatenate([[0], np.cumsum(~white)])
    has = filled[end] > filled[begin]
    line_row = np.repeat(np.arange(n), lines)[has]
    lines = np.bincount(line_row, minlength=n)
    _, _, kinds = kernel.distinct(kernel.word_hashes(data, begin[has], end[has]), lines)
    out["n_lines"], out["n_dup_lines"] = lines, lines - kinds
    # Words in windows of three that a row has twice or more.
    grams, counts = kernel.windows(hashes, words, 3)
    gram_row = np.repeat(np.arange(n), counts)
    order = np.lexsort((grams, gram_row))
    same = (grams[order][1:] == grams[order][:-1]) & (gram_row[order][1:] == gram_row[order][:-1])
    twice = np.zeros(len(grams), dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    first = (np.cumsum(words) - words)[gram_row] + np.arange(len(grams)) - (np.cumsum(counts) - counts)[gram_row]
    covered = np.zeros(len(hashes), dtype=bool)
    for j in range(3):
        covered[first[twice] + j] = True
    out["n_repeat_words"] = np.bincount(row[covered], minlength=n)
    return out


def _row_max(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    out = np.zeros(len(counts), dtype=np.int64)
    has = np.flatnonzero(counts)
    if len(has):
        out[has] = np.maximum.reduceat(values, (np.cumsum(counts) - counts)[has])
    return out


def measure(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The counts and ratios of every document."""
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType), *(T.StructField(c, T.LongType()) for c in COUNTS)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, column in arrow.text_chunks(batches, "text"):
            found = statistics(*arrow.text_buffers(column))
            yield pa.RecordBatch.from_arrays([part.column("id"), *(pa.array(found[c].astype(np.int64)) for c in COUNTS)], names=schema.names)

    counted = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, schema)
    return counted.withColumns({name: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0)) for name, (a, b) in RATIOS.items()})


@dataclass(frozen=True)
class Condition:
    feature: str
    at_least: bool
    value: float

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.feature] >= self.value if self.at_least else x[self.feature] <= self.value

    def column(self) -> Column:
        return F.col(self.feature) >= self.value if self.at_least else F.col(self.feature) <= self.value

    def __str__(self) -> str:
        return f"{self.feature} {'>=' if self.at_least else '<='} {self.value:.6g}"


Rule = tuple[Condition, ...]


def covers(rule: Rule, x: dict[str, np.ndarray]) -> np.ndarray:
    out = np.ones(len(next(iter(x.values()))), dtype=bool)
    for c in rule:
        out &= c.holds(x)
    return out


def _thresholds(values: np.ndarray) -> np.ndarray:
    distinct = np.unique(values)
    middle = (distinct[1:] + distinct[:-1]) / 2
    return middle if len(middle) <= THRESHOLDS else np.unique(np.quantile(middle, np.linspace(0, 1, THRESHOLDS)))


def _grow(x: dict[str, np.ndarray], bad: np.ndarray) -> Rule:
    """Adds the condition of most information gain until no good document is covered."""
    rule: list[Condition] = []
    inside = np.ones(len(bad), dtype=bool)
    while len(rule) < CONDITIONS and (inside & ~bad).any():
        p, n = (inside & bad).sum(), (inside & ~bad).sum()
        best, gain = None, 1e-9
        for feature in FEATURES:
            v, b = x[feature][inside], bad[inside]
            for cut in _thresholds(v):
                for up in (True, False):
                    hit = v >= cut if up else v <= cut
                    p1 = (hit & b).sum()
                    if p1 < LEAST:
                        continue
                    got = p1 * (np.log2(p1 / hit.sum()) - np.log2(p / (p + n)))
                    if got > gain:
                        best, gain = Condition(feature, up, float(cut)), got
        if best is None:
            break
        rule.append(best)
        inside &= best.holds(x)
    return tuple(rule)


def _worth(rule: Rule, x: dict[str, np.ndarray], bad: np.ndarray) -> float:
    inside = covers(rule, x)
    p, n = (inside & bad).sum(), (inside & ~bad).sum()
    return (p - n) / (p + n) if p + n else -1.0


def _prune(rule: Rule, x: dict[str, np.ndarray], bad: np.ndarray) -> Rule:
    """Drops final conditions while the rule is worth as much on documents it wasn't grown on."""
    best, most = rule, _worth(rule, x, bad)
    for k in range(len(rule) - 1, 0, -1):
        if (worth := _worth(rule[:k], x, bad)) >= most:
            best, most = rule[:k], worth
    return best


def learn(x: dict[str, np.ndarray], bad: np.ndarray) -> list[Rule]:
    """Ordered rules that reject; documents that no rule covers are kept."""
    part = np.arange(len(bad)) % 3 == 2
    rules: list[Rule] = []
    left = np.ones(len(bad), dtype=bool)
    while len(rules) < RULES and (left & bad & ~part).sum() >= LEAST:
        grow, prune = left & ~part, left & part
        rule = _grow({k: v[grow] for k, v in x.items()}, bad[grow])
        if not rule:
            break
        rule = _prune(rule, {k: v[prune] for k, v in x.items()}, bad[prune])
        inside = covers(rule, x) & left
        if inside.sum() < LEAST or bad[inside].mean() < PRECISION:
            break
        rules.append(rule)
        left &= ~inside
    return rules


def expression(rules: list[Rule]) -> Column:
    """Number, from 1, of the first rule that rejects; null if none does."""
    out = F.lit(None).cast("int")
    for k in range(len(rules), 0, -1):
        every = F.lit(True)
        for c in rules[k - 1]:
            every = every & c.column()
        out = F.when(every, F.lit(k)).otherwise(out)
    return out


def fit(measured: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", label_col: str = "quality", sample: int = SAMPLE) -> list[Rule]:
    """Learn from the labelled documents among ``measured``; label 0 is bad."""
    known = labels.where(F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("doc_id")).agg(F.min(label_col).alias("__label"))
    place = F.xxhash64("doc_id", *FEATURES).bitwiseAND(2**40 - 1) / 2**40
    # Repeated rows teach once, so that many of one id can't exceed the sample.
    rows = materialise(measured.select("doc_id", *FEATURES).join(known, "doc_id").distinct().withColumn("__place", place), "quality-labelled")
    drawn = rows.where(F.col("__place") < sample / max(1, rows.count())).limit(2 * sample)
    rows = drawn.toPandas().sort_values(["__place", *FEATURES])
    bad = (rows["__label"] == 0).to_numpy(dtype=bool)
    if not bad.any() or bad.all():
        return []
    return learn({f: rows[f].to_numpy(np.float64) for f in FEATURES}, bad)


def judge(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> DataFrame:
    """Counts, the base rules' result, the verdict and the rule that rejected."""
    measured = materialise(measure(docs, id_col=id_col, text_col=text_col), "quality")
    rules = fit(measured, labels, label_col=label_col)
    failed = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > REPEATED_PERCENT * F.col("n_words"))
    judged = measured.withColumn("base_failed", failed).withColumn("rule", expression(rules))
    names = F.array(*[F.lit(" and ".join(map(str, r))) for r in rules]) if rules else F.array().cast("array<string>")
    return judged.withColumn("kept", ~F.col("base_failed") & F.col("rule").isNull()).withColumn("rule_text", F.get(names, F.col("rule") - 1))
