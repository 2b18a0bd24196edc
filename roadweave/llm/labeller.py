"""Recurrent block labeller: main text or boilerplate, for every block of a page.

A page is the sequence of its leaf blocks. A block's vector has the tags of its
path and the words of their class, id and role attributes, hashed words of its
text, and a few numbers (length, share in links, place). A bidirectional LSTM
in numpy reads the whole sequence, so each block is judged with all of the page
in view. It is trained here, on pages that :mod:`pagemaker` writes, with a fixed
seed: no page of any table is used for training.

Defined results: null or empty html and pages without blocks give an empty
text; repeated rows are read each; null ids stay null; broken html is read as
far as it goes, a tag that never closes as text, in time that follows its length; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from . import arrow
from .blocks import Block, Place, blocks
from .pagemaker import PageMaker

TAG_DIM, WORD_DIM, NUMBERS = 96, 48, 6
HIDDEN = 20
#: Training: pages, passes over them, pages at a time, seed.
PAGES, PASSES, AT_ONCE, SEED = 2000, 8, 25, 11
#: Blocks that one forward pass holds at most, unless a single page has more.
CELLS = 20_000
#: Tags that stand beside hashing, as they tell most.
TOLD = ("article", "main", "nav", "header", "footer", "aside", "form", "section", "p", "li", "a", "h1", "h2", "h3", "td", "blockquote", "button", "label")


@lru_cache(maxsize=50_000)
def _slot(kind: str, word: str) -> tuple[int, float]:
    h = zlib.crc32(f"{kind}:{word}".encode())
    if kind == "w":
        return TAG_DIM + (h >> 1) % WORD_DIM, 1.0 if h & 1 else -1.0
    if kind == "t" and word in TOLD:
        return TOLD.index(word), 1.0
    return len(TOLD) + (h >> 1) % (TAG_DIM - len(TOLD)), 1.0


def _slots(place: Place | None) -> int:
    """Slots of an element and of all above it as bits; each element is looked at once a page."""
    line = []
    while place is not None and place.slots is None:
        line.append(place)
        place = place.above
    bits = 0 if place is None else place.slots
    for p in reversed(line):
        bits |= 1 << _slot("t", p.tag)[0]
        for w in p.words:
            bits |= 1 << _slot("c", w)[0]
        p.slots = bits
    return bits


@lru_cache(maxsize=20_000)
def _places(bits: int) -> tuple[int, ...]:
    return tuple(i for i in range(TAG_DIM) if bits >> i & 1)


def vectors(page: list[Block]) -> np.ndarray:
    """One row per block; every word of its text counts, as a share of them all."""
    out = np.zeros((len(page), TAG_DIM + WORD_DIM + NUMBERS), dtype=np.float32)
    last = max(1, len(page) - 1)
    at, share, rows = [], [], []
    for i, b in enumerate(page):
        out[i, list(_places(_slots(b.place)))] = 1.0
        tokens = b.text.lower().split(" ")
        for w in tokens:
            slot, sign = _slot("w", w)
            at.append(slot)
            share.append(sign / len(tokens))
        rows.append(len(tokens))
        out[i, TAG_DIM + WORD_DIM :] = (np.log1p(len(b.text)) / 6, np.log1p(len(tokens)) / 4, b.linked, i / last, float(b.text[-1:] in ".!?"), 1.0)
    np.add.at(out, (np.repeat(np.arange(len(page)), rows), np.array(at, dtype=np.int64)), np.array(share, dtype=np.float32))
    return out


def padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sequences of one batch, time first, and which places are real."""
    longest = max(len(p) for p in pages)
    x = np.zeros((longest, len(pages), pages[0].shape[1]), dtype=np.float32)
    mask = np.zeros((longest, len(pages), 1), dtype=np.float32)
    for i, p in enumerate(pages):
        x[: len(p), i] = p
        mask[: len(p), i] = 1
    return x, mask


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Direction:
    """An LSTM that reads in one direction; masked places keep its state."""

    def __init__(self, rng: np.random.Generator, size: int):
        scale = (size + HIDDEN) ** -0.5
        self.w = rng.normal(0, scale, (size, 4 * HIDDEN)).astype(np.float32)
        self.u = rng.normal(0, scale, (HIDDEN, 4 * HIDDEN)).astype(np.float32)
        self.b = np.zeros(4 * HIDDEN, dtype=np.float32)
        self.b[HIDDEN : 2 * HIDDEN] = 1
        self.names = ("w", "u", "b")

    def forward(self, x: np.ndarray, mask: np.ndarray, taped: bool = True) -> tuple[np.ndarray, list]:
        n = x.shape[1]
        h = c = np.zeros((n, HIDDEN), dtype=np.float32)
        inputs = x @ self.w + self.b
        out, tape = np.empty((len(x), n, HIDDEN), dtype=np.float32), []
        for t in range(len(x)):
            gates = inputs[t] + h @ self.u
            i, f, o = (_sigmoid(gates[:, k * HIDDEN : (k + 1) * HIDDEN]) for k in range(3))
            g = np.tanh(gates[:, 3 * HIDDEN :])
            c2 = f * c + i * g
            tc = np.tanh(c2)
            h2 = o * tc
            if taped:
                tape.append((h, c, i, f, o, g, tc))
            m = mask[t]
            h, c = m * h2 + (1 - m) * h, m * c2 + (1 - m) * c
            out[t] = h
        return out, tape

    def backward(self, x: np.ndarray, mask: np.ndarray, tape: list, upper: np.ndarray) -> dict[str, np.ndarray]:
        n = x.shape[1]
        dh = dc = np.zeros((n, HIDDEN), dtype=np.float32)
        dgates = np.empty((len(x), n, 4 * HIDDEN), dtype=np.float32)
        du = np.zeros_like(self.u)
        for t in range(len(x) - 1, -1, -1):
            h, c, i, f, o, g, tc = tape[t]
            m = mask[t]
            dh = dh + upper[t]
            own_h, own_c = m * dh, m * dc
            own_c = own_c + own_h * o * (1 - tc * tc)
            d = dgates[t]
            d[:, :HIDDEN] = own_c * g * i * (1 - i)
            d[:, HIDDEN : 2 * HIDDEN] = own_c * c * f * (1 - f)
            d[:, 2 * HIDDEN : 3 * HIDDEN] = own_h * tc * o * (1 - o)
            d[:, 3 * HIDDEN :] = own_c * i * (1 - g * g)
            du += h.T @ d
            dh = (1 - m) * dh + d @ self.u.T
            dc = (1 - m) * dc + own_c * f
        flat = dgates.reshape(-1, 4 * HIDDEN)
        return {"w": x.reshape(-1, x.shape[2]).T @ flat, "u": du, "b": flat.sum(axis=0)}


class Labeller:
    """Two directions and a logistic layer over both."""

    def __init__(self, seed: int = SEED):
        rng = np.random.default_rng(seed)
        size = TAG_DIM + WORD_DIM + NUMBERS
        self.ahead, self.back = Direction(rng, size), Direction(rng, size)
        self.v = rng.normal(0, 0.2, (2 * HIDDEN, 1)).astype(np.float32)
        self.d = np.zeros(1, dtype=np.float32)

    def _forward(self, x: np.ndarray, mask: np.ndarray, taped: bool = True):
        a, tape_a = self.ahead.forward(x, mask, taped)
        b, tape_b = self.back.forward(x[::-1], mask[::-1], taped)
        state = np.concatenate([a, b[::-1]], axis=2)
        return _sigmoid(state @ self.v + self.d), state, tape_a, tape_b

    def _gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray) -> dict:
        p, state, tape_a, tape_b = self._forward(x, mask)
        error = (p - y) * mask / mask.sum()
        upper = error @ self.v.T
        out = {(self, "v"): state.reshape(-1, 2 * HIDDEN).T @ error.reshape(-1, 1), (self, "d"): error.sum(axis=(0, 1))}
        out |= {(self.ahead, k): g for k, g in self.ahead.backward(x, mask, tape_a, upper[:, :, :HIDDEN]).items()}
        out |= {(self.back, k): g for k, g in self.back.backward(x[::-1], mask[::-1], tape_b, upper[::-1, :, HIDDEN:]).items()}
        return out

    def fit(self, pages: list[tuple[np.ndarray, np.ndarray]], passes: int = PASSES, rate: float = 0.01) -> None:
        """Adam over batches of pages of similar length."""
        order = sorted(range(len(pages)), key=lambda i: len(pages[i][0]))
        batches = []
        for k in range(0, len(order), AT_ONCE):
            own = [pages[i] for i in order[k : k + AT_ONCE]]
            x, mask = padded([p for p, _ in own])
            y, _ = padded([q[:, None] for _, q in own])
            batches.append((x, mask, y))
        rng, moment, step = np.random.default_rng(SEED), {}, 0
        for done in range(passes):
            for k in rng.permutation(len(batches)):
                step += 1
                x, mask, y = batches[k]
                # Half of all blocks are learned without their words: the made words are few, and the layout tells more.
                x = x.copy()
                x[:, :, TAG_DIM : TAG_DIM + WORD_DIM] *= rng.random(mask.shape) < 0.5
                now = rate * (1 - done / passes) + 0.001
                for (owner, name), g in self._gradients(x, mask, y).items():
                    g = np.clip(g, -1, 1)
                    m, s = moment.get((id(owner), name), (0.0, 0.0))
                    m, s = 0.9 * m + 0.1 * g, 0.99 * s + 0.01 * g * g
                    moment[id(owner), name] = m, s
                    getattr(owner, name)[...] -= now * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-8)

    def label(self, pages: list[np.ndarray]) -> list[np.ndarray]:
        """Probability of main text for every block of every page."""
        out: list[np.ndarray] = [np.zeros(0)] * len(pages)
        order = [i for i in sorted(range(len(pages)), key=lambda i: len(pages[i])) if len(pages[i])]
        at = 0
        while at < len(order):
            stop = at + 1
            while stop < len(order) and (stop - at + 1) * len(pages[order[stop]]) <= CELLS:
                stop += 1
            own = order[at:stop]
            p = self._forward(*padded([pages[i] for i in own]), taped=False)[0]
            for k, i in enumerate(own):
                out[i] = p[: len(pages[i]), k, 0]
            at = stop
        return out


def labelled(page: list[Block], known: list[tuple[str, int]]) -> np.ndarray:
    """Labels of a made page's blocks; its texts come in the same order."""
    return np.array([label for block, (text, label) in zip(page, known, strict=True)], dtype=np.float32)


@lru_cache(maxsize=1)
def trained() -> Labeller:
    maker, pages = PageMaker(SEED), []
    for _ in range(PAGES):
        text, known = maker.page()
        page = blocks(text)
        pages.append((vectors(page), labelled(page, known)))
    model = Labeller()
    model.fit(pages)
    return model


def main_text(pages: list[str], model: Labeller) -> list[str]:
    parsed = [blocks(p) for p in pages]
    marks = model.label([vectors(p) for p in parsed])
    return ["\n".join(b.text for b, m in zip(page, own) if m > 0.5) for page, own in zip(parsed, marks)]


def extract(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """The main text of every page and its code points."""
    model = pages.sparkSession.sparkContext.broadcast(trained())
    schema = T.StructType([T.StructField("page_id", pages.schema[id_col].dataType), T.StructField("url", T.StringType()), T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, column in arrow.text_chunks(batches, "html"):
            texts = main_text([p or "" for p in column.to_pylist()], model.value)
            yield pa.RecordBatch.from_arrays([part.column("id"), part.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=schema.names)

    own = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return own.mapInArrow(run, schema)
