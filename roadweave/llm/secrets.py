"""Secret scans: patterns and sliding-window entropy, in DataFrame functions alone.

Base kinds are matches of three patterns. The method adds ``entropy`` spans:
candidate strings are maximal runs of key characters; each belongs to a class
by the characters it has, and a window slides over it whose Shannon entropy
follows from that of the window before by one character in and one out. Windows at
or over the threshold of their class join to a span. Words, identifiers with a
fixed form and known placeholders are on the allow-list and suppressed.

With S the sum of c * log2(c) over the counts c of a window of W characters,
its entropy is log2(W) - S / W; a character that comes or goes changes one term.
Long runs are read in pieces that overlap by a window less one, and arrays of spans
grow by blocks, so the work is in proportion to a text's length.

Defined results: null counts as empty; an empty text has no spans and the
SHA-256 of no bytes; repeated rows are scanned each; null ids stay null; an
empty table gives an empty table; other columns, whatever their names, are kept by
:func:`redact` and ignored otherwise.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, functions as F

from . import losers


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: Fixed patterns of the base kinds, in the order that breaks ties of a start.
ASSIGN = "(" + "|".join(_either_case(w) for w in ("password", "passwd", "secret", "token", "api_?key")) + r""")["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = "AKIA[A-Z0-9]+"
HEX = "[0-9a-f]+"
ASSIGN_VALUE, ACCESS_LENGTH, HEX_LENGTH = 12, 18, 16
KINDS = ("assign", "access", "hex", "entropy")

#: Window, and the entropy in bits from which a window of a class counts.
WINDOW = 20
CLASS_BITS = {"hex": 3.0, "single": 3.6, "mixed": 3.7}
CANDIDATE = "[A-Za-z0-9+/_=-]{20,}"
#: Allow-list: fixed forms, and placeholders in runs that are too short to have them by chance.
ALLOWED = (
    "^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    "(?i)^.{0,200}(example|sample|dummy|placeholder|changeme|redacted|your[_-]).{0,200}$",
    "(?i)^.{0,200}(0123456789|abcdefghij|qwertyuiop).{0,200}$",
    "^[0-9+/_=-]+$",
    "^[A-Za-z+/_=-]+$",
    "^[a-z]+([-_/]([a-z]+|[0-9]+)){1,200}$",
)
#: Windows of one piece of a run, and elements of one block of an array.
PIECE, BLOCK = 64, 256
_SPANS = "array<struct<start:int,end:int,hit:string,rank:int>>"


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once: lambdas compute what they take from outside at every step."""
    return F.get(F.transform(F.array(value), use), 0)


def _folded(values: Column, zero: Column, step: Callable[[Column, Column], tuple[Column, Column]], kind: str) -> Column:
    """Elements that ``step(state, value)`` gives besides the next state; those that are null are left out.

    Elements are gathered by blocks, as every addition copies the array.
    """
    none = F.array().cast(f"array<{kind}>")

    def one(state: Column, value: Column) -> Column:
        now, made = step(state["now"], value)
        return F.struct(now.alias("now"), F.when(made.isNull(), state["out"]).otherwise(F.concat(state["out"], F.array(made))).alias("out"))

    def block(state: Column, own: Column) -> Column:
        inner = F.aggregate(own, F.struct(state["now"].alias("now"), none.alias("out")), one)
        return _let(inner, lambda x: F.struct(x["now"].alias("now"), F.concat(state["out"], x["out"]).alias("out")))

    def whole(every: Column) -> Column:
        starts = F.when(F.size(every) > 0, F.sequence(F.lit(1), F.size(every), F.lit(BLOCK))).otherwise(F.array().cast("array<int>"))
        blocks = F.transform(starts, lambda k: F.slice(every, k, BLOCK))
        return F.aggregate(blocks, F.struct(zero.alias("now"), none.alias("out")), block, lambda x: x["out"])

    return _let(values, whole)


def _spans(text: Column, pattern: str, kind: str, keep: Callable[[Column], Column]) -> Column:
    """Spans of the leftmost non-overlapping matches that pass ``keep(match)``.

    Splitting by the pattern gives the text between matches; lengths of these
    and of the matches add up to places in code points.
    """
    parts = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hit"))

    def step(at: Column, part: Column) -> tuple[Column, Column]:
        begin = at + F.length(part["gap"])
        end = begin + F.coalesce(F.length(part["hit"]), F.lit(0))
        span = F.struct(begin.alias("start"), end.alias("end"), part["hit"].alias("hit"), F.lit(KINDS.index(kind)).alias("rank"))
        return end, F.when(F.coalesce(keep(part["hit"]), F.lit(False)), span)

    found = _folded(parts, F.lit(0), step, _SPANS[len("array<") : -1])
    return F.when(F.regexp_like(text, F.lit(pattern)), found).otherwise(F.array().cast(_SPANS))


def base_spans(text: Column) -> dict[str, Column]:
    """Spans of each base kind.

    Runs of the access and hex patterns are maximal, so asking for their least
    length in the pattern finds the same matches as dropping shorter ones. An
    assignment that fails may hide a later one, so those are dropped after.
    """
    value = lambda hit: F.length(F.regexp_extract(hit, ASSIGN, 2)) >= ASSIGN_VALUE
    return {
        "assign": _spans(text, ASSIGN, "assign", value),
        "access": _spans(text, f"AKIA[A-Z0-9]{{{ACCESS_LENGTH - 4},}}", "access", lambda hit: hit.isNotNull()),
        "hex": _spans(text, f"(?<![0-9a-f])[0-9a-f]{{{HEX_LENGTH},}}", "hex", lambda hit: hit.isNotNull()),
    }


def _class_bits(run: Column) -> Column:
    """Threshold of a candidate's class; null where the allow-list suppresses it."""
    allowed = F.lit(False)
    for pattern in ALLOWED:
        allowed = allowed | F.regexp_like(run, F.lit(pattern))
    lower, upper, digit = (F.regexp_like(run, F.lit(p)) for p in ("[a-z]", "[A-Z]", "[0-9]"))
    return (
        F.when(allowed, F.lit(None).cast("double"))
        .when(F.regexp_like(run, F.lit("^([0-9a-f]+|[0-9A-F]+)$")), CLASS_BITS["hex"])
        .when(lower & upper & digit, CLASS_BITS["mixed"])
        .otherwise(CLASS_BITS["single"])
    )


def windows_over(run: Column, bits: Column, window: int = WINDOW) -> Column:
    """First and last start of the windows of ``run`` whose entropy is ``bits`` or more; nulls if there is none."""
    weight = [n * math.log2(n) if n else 0.0 for n in range(window + 1)]
    # What the sum gains when a character comes to n others of its kind; as much is lost when it goes.
    gain = F.array(*[F.lit(b - a) for a, b in zip(weight[:-1], weight[1:])])
    pieces = F.regexp_extract_all(run, F.lit(f"(?=(.{{1,{PIECE + window - 1}}})).{{1,{PIECE}}}"), F.lit(1))
    places = F.sequence(F.lit(1), F.lit(PIECE + window - 1))

    def of_piece(piece: Column) -> Column:
        """First and last start in a piece, from 0; the characters around a place are read from the piece itself."""

        def total(before: Column, i: Column) -> Column:
            came, gone = F.substring(piece, i, 1), F.when(i > window, F.substring(piece, i - window, 1))
            others = F.substring(piece, F.greatest(i - (window - 1), F.lit(1)), F.least(i, F.lit(window)) - 1)

            def alike(text: Column, c: Column) -> Column:
                return F.length(text) - F.length(F.replace(text, c, F.lit("")))

            return _let(others, lambda o: before + F.get(gain, alike(o, came)) - F.coalesce(F.get(gain, alike(o, gone)), F.lit(0.0)))

        def step(state: Column, i: Column) -> Column:
            def now(s: Column) -> Column:
                over = (i >= window) & (F.lit(math.log2(window)) - s / window >= bits - 1e-9)
                return _let(F.when(over, i - window), lambda at: F.struct(s.alias("s"), F.coalesce(state["first"], at).alias("first"), F.coalesce(at, state["last"]).alias("last")))

            return _let(total(state["s"], i), now)

        none = F.lit(None).cast("int")
        zero = F.struct(F.lit(0.0).alias("s"), none.alias("first"), none.alias("last"))
        return F.aggregate(F.slice(places, F.lit(1), F.length(piece)), zero, step)

    found = F.transform(pieces, lambda piece, k: F.struct(k.alias("k"), of_piece(piece).alias("w")))
    spans = F.transform(found, lambda x: F.struct((x["k"] * PIECE + x["w"]["first"]).alias("first"), (x["k"] * PIECE + x["w"]["last"]).alias("last")))
    return F.struct(F.array_min(F.transform(spans, lambda x: x["first"])).alias("first"), F.array_max(F.transform(spans, lambda x: x["last"])).alias("last"))


def entropy_spans(text: Column) -> Column:
    """Spans that only their entropy gives away."""
    runs = _spans(text, f"(?<![A-Za-z0-9+/_=-]){CANDIDATE}", "entropy", lambda hit: _class_bits(hit).isNotNull())
    classed = F.transform(runs, lambda x: F.struct(x.alias("run"), _class_bits(x["hit"]).alias("bits")))
    timed = F.transform(classed, lambda x: F.struct(x["run"].alias("run"), windows_over(x["run"]["hit"], x["bits"]).alias("w")))
    over = F.filter(timed, lambda x: x["w"]["first"].isNotNull())
    return F.transform(
        over,
        lambda x: F.struct(
            (x["run"]["start"] + x["w"]["first"]).alias("start"),
            (x["run"]["start"] + x["w"]["last"] + WINDOW).alias("end"),
            x["run"]["hit"].alias("hit"),
            x["run"]["rank"].alias("rank"),
        ),
    )


def _ordered(spans: Column) -> Column:
    return F.array_sort(F.transform(spans, lambda x: F.struct(x["start"].alias("start"), x["rank"].alias("rank"), x["end"].alias("end"))))


def _joined(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["rank"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def _uncovered(spans: Column) -> Column:
    """Ordered spans without the entropy spans that lie in a base span: none that began before or there reaches as far."""

    def step(reach: Column, span: Column) -> tuple[Column, Column]:
        base = span["rank"] < len(KINDS) - 1
        return F.when(base, F.greatest(reach, span["end"])).otherwise(reach), F.when(base | (span["end"] > reach), span)

    return _folded(spans, F.lit(-1), step, "struct<start:int,rank:int,end:int>")


def with_spans(docs: DataFrame, *, text_col: str = "text") -> tuple[DataFrame, str]:
    """``docs`` with a struct of a name of its own: the text, spans by base kind, and ordered arrays of (start, rank, end), ``base`` and ``all``."""
    name = losers.fresh(docs, "secrets")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    found = docs.withColumn(name, F.struct(text.alias("text")))
    own = F.col(f"{name}.text")
    found = found.withColumn(name, F.struct(own.alias("text"), *[spans.alias(kind) for kind, spans in base_spans(own).items()], entropy_spans(own).alias(KINDS[-1])))
    base = _ordered(F.concat(*[F.col(f"{name}.{k}") for k in KINDS[:-1]]))
    found = found.withColumn(name, F.col(name).withField("base", base))
    every = F.array_sort(F.concat(F.col(f"{name}.base"), _ordered(F.col(f"{name}.{KINDS[-1]}"))))
    return found.withColumn(name, F.col(name).withField("all", F.when(F.size(f"{name}.{KINDS[-1]}") > 0, _uncovered(every)).otherwise(F.col(f"{name}.base")))), name


def scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: counts by base kind, a digest of the base spans, and all spans."""
    found, own = with_spans(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")))
    return found.select(
        "doc_id",
        *[F.size(f"{own}.{k}").cast("long").alias(f"n_{k}") for k in KINDS[:-1]],
        F.sha2(_joined(F.col(f"{own}.base")), 256).alias("base_sha256"),
        _joined(F.col(f"{own}.all")).alias("spans"),
        (F.size(f"{own}.all") - F.size(f"{own}.base")).cast("long").alias("n_entropy"),
    )


def redact(docs: DataFrame, *, text_col: str = "text", mask: str = "[secret]") -> DataFrame:
    """The documents with every found span, overlapping ones as one, replaced by ``mask``; all columns stay."""
    names = docs.columns
    found, own = with_spans(docs, text_col=text_col)
    text, spans = F.col(f"{own}.text"), F.col(f"{own}.all")

    def step(at: Column, span: Column) -> tuple[Column, Column]:
        gap = F.struct(at.alias("start"), (span["start"] - at).alias("length"))
        return F.greatest(at, span["end"]), F.when(span["start"] >= at, gap)

    last = F.array_max(F.transform(spans, lambda x: x["end"]))
    gaps = F.concat(_folded(spans, F.lit(0), step, "struct<start:int,length:int>"), F.array(F.struct(last.alias("start"), (F.length(text) - last).alias("length"))))
    # Four bytes a code point: a piece is found without reading what is before it.
    pieces = _let(F.encode(text, "UTF-32"), lambda wide: F.transform(gaps, lambda g: F.decode(F.substring(wide, g["start"] * 4 + 1, g["length"] * 4), "UTF-32")))
    return found.withColumn(text_col, F.when(F.size(spans) > 0, F.array_join(pieces, mask)).otherwise(F.col(text_col))).select(*losers.quoted(names))
