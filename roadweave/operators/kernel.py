"""Co-clustering of a matrix that fits one task: merges, exchanges and restarts in numpy.

The state is a block matrix with its margins. The change of cost by a merge or
a move touches the blocks of the clusters concerned and terms of their margins;
for merges it is kept for all pairs and updated as blocks change.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from ..functions.scalar import log_partitions


#: Entries of a model's own table of ln n! at most.
TABLE = 4_000_000
#: ln n! of small counts; larger ones are by Stirling's series, so no table grows with the visits.
SMALL = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, 1 << 16)))])


def log_factorials(n: np.ndarray) -> np.ndarray:
    """ln n! of any counts, by table and by Stirling's series beyond it."""
    n = np.asarray(n)
    out = np.asarray(SMALL[np.minimum(n, len(SMALL) - 1)])
    large = n >= len(SMALL)
    if large.any():
        out = out.reshape(n.shape)
        x = n[large].astype(np.float64)
        out[large] = x * np.log(x) - x + 0.5 * np.log(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * x**3)
    return out


class LogFactorials:
    """ln n!, by a table where it is small enough."""

    def __init__(self, n: int):
        self.table = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, max(2, n) + 1)))]) if n < TABLE else None

    def __call__(self, n):
        return log_factorials(n) if self.table is None else self.table[n]


def best_clusters(block: np.ndarray, size: np.ndarray, mass: np.ndarray, rows: list[tuple[int, np.ndarray, np.ndarray]]) -> list[int]:
    """For each vertex ``(its cluster, cells, visits in them)`` the cluster of least cost, all others held still.

    ``block`` has a line for every cluster of the vertices' side. Of equal costs
    the own cluster is taken, then the first.
    """
    f = log_factorials(block)
    margin = lambda size, mass: log_factorials(mass + size - 1) - log_factorials(np.maximum(size - 1, 0))
    alone = np.where(size > 0, margin(size, mass), 0.0)
    out = []
    for c, cells, n in rows:
        degree = int(n.sum())
        near, then = block[:, cells], f[:, cells]
        delta = (then - log_factorials(near + n)).sum(axis=1) + margin(size + 1, mass + degree) - alone
        kept = near[c] - n
        left = margin(size[c] - 1, mass[c] - degree) if size[c] > 1 else 0.0
        delta[c] = (log_factorials(kept) - then[c]).sum() + margin(size[c], mass[c]) - left
        delta = np.round(delta, 9)
        to = int(delta.argmin())
        out.append(c if delta[c] <= delta[to] else to)
    return out


def best_moves(block: np.ndarray, size: np.ndarray, mass: np.ndarray, own: np.ndarray, begin: np.ndarray, cell: np.ndarray, n: np.ndarray) -> np.ndarray:
    """:func:`best_clusters` of many vertices: ``own`` is the cluster of each, and its cells and visits follow from ``begin``."""
    turned = np.ascontiguousarray(block.T)
    wide, k = turned.shape
    f = log_factorials(turned)
    # Changes by few visits more are looked up.
    few = int(min(max(1, 4_000_000 // max(1, turned.size)), 64, n.max(initial=1)))
    table = np.concatenate([f - log_factorials(turned + x) for x in range(1, few + 1)])
    line_cost = lambda size, mass: log_factorials(mass + size - 1) - log_factorials(np.maximum(size - 1, 0))
    alone = np.where(size > 0, line_cost(size, mass), 0.0)
    each = np.diff(np.append(begin, len(cell)))
    degree = np.add.reduceat(n, begin)
    mine = np.repeat(own, each)
    kept = turned[cell, mine] - n
    stay = np.add.reduceat(log_factorials(kept) - f[cell, mine], begin)
    left = np.where(size[own] > 1, line_cost(np.maximum(size[own] - 1, 1), mass[own] - degree), 0.0)
    stay += line_cost(size[own], mass[own]) - left
    out = np.empty(len(own), np.int64)
    ends = begin + each
    start = 0
    while start < len(own):
        stop = min(len(own), start + max(1, 1_000_000 // max(wide, k)))
        a, b = int(begin[start]), int(ends[stop - 1])
        c, m, line = cell[a:b], n[a:b], np.repeat(np.arange(stop - start), each[start:stop])
        delta = np.zeros((stop - start, k))
        rest = np.ones(len(c), bool)
        for x in np.flatnonzero(np.bincount(np.minimum(m, few + 1), minlength=few + 2)[: few + 1] * 100 > (stop - start) * wide):
            # Where many vertices have this number of visits somewhere, a product of matrices adds them up.
            own_cells, now = np.zeros((stop - start, wide)), m == x
            own_cells[line[now], c[now]] = 1
            delta += own_cells @ table[(x - 1) * wide : x * wide]
            rest &= ~now
        c, m, line = c[rest], m[rest], line[rest]
        # Cells by clusters stay in the processor's cache.
        at_once = max(1, 500_000 // k)
        for low in range(0, len(c), at_once):
            d, x, own_line = c[low : low + at_once], m[low : low + at_once], line[low : low + at_once]
            terms = table[np.where(x <= few, x - 1, 0) * wide + d]
            if (high := np.flatnonzero(x > few)).size:
                terms[high] = f[d[high]] - log_factorials(turned[d[high]] + x[high][:, None])
            first = np.flatnonzero(np.append(True, own_line[1:] != own_line[:-1]))
            delta[own_line[first]] += np.add.reduceat(terms, first)
        degrees, which = np.unique(degree[start:stop], return_inverse=True)
        delta += (line_cost(size[None, :] + 1, mass[None, :] + degrees[:, None]) - alone)[which]
        row = np.arange(stop - start)
        delta[row, own[start:stop]] = stay[start:stop]
        delta = np.round(delta, 9)
        to = delta.argmin(axis=1)
        out[start:stop] = np.where(delta[row, own[start:stop]] <= delta[row, to], own[start:stop], to)
        start = stop
    return out


def _choose(n: float, k: float) -> float:
    return math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)


@dataclass
class Side:
    """One side's clusters: label of each vertex, and per cluster its vertices and visits."""

    label: np.ndarray
    size: np.ndarray
    mass: np.ndarray
    alive: np.ndarray = field(init=False)

    def __post_init__(self) -> None:
        self.alive = self.size > 0

    @property
    def k(self) -> int:
        return int(self.alive.sum())


class Model:
    """A co-clustering of a matrix of counts, dense over clusters."""

    def __init__(self, t: np.ndarray, s: np.ndarray, n: np.ndarray, rows: np.ndarray, columns: np.ndarray):
        """Edges by vertex numbers from 0, and a start label for every row and column."""
        self.t, self.s, self.n = t, s, n
        self.m = int(n.sum())
        self.log_f = LogFactorials(2 * (self.m + len(rows) + len(columns)) + 2)
        self.row_n = np.bincount(t, weights=n, minlength=len(rows)).astype(np.int64)
        self.col_n = np.bincount(s, weights=n, minlength=len(columns)).astype(np.int64)
        self.fixed = -self.log_f(self.row_n).sum() - self.log_f(self.col_n).sum()
        self.set(rows, columns)

    def set(self, rows: np.ndarray, columns: np.ndarray) -> None:
        _, rows = np.unique(rows, return_inverse=True)
        _, columns = np.unique(columns, return_inverse=True)
        kt, ks = rows.max() + 1, columns.max() + 1
        self.block = np.zeros((kt, ks), dtype=np.int64)
        np.add.at(self.block, (rows[self.t], columns[self.s]), self.n)
        self.rows = Side(rows.copy(), np.bincount(rows, minlength=kt), np.bincount(rows, weights=self.row_n, minlength=kt).astype(np.int64))
        self.columns = Side(columns.copy(), np.bincount(columns, minlength=ks), np.bincount(columns, weights=self.col_n, minlength=ks).astype(np.int64))

    def _margin(self, size, mass):
        """Terms of a cluster's margin: counts of its vertices, and visits into them."""
        return self.log_f(mass + size - 1) - self.log_f(size - 1)

    def _partitions(self, kt: int, ks: int) -> float:
        cells = kt * ks
        return log_partitions(len(self.rows.label), kt) + log_partitions(len(self.columns.label), ks) + _choose(self.m + cells - 1, cells - 1)

    def cost(self) -> float:
        rows, columns = self.rows, self.columns
        a, b = rows.alive, columns.alive
        out = math.log(len(rows.label)) + math.log(len(columns.label)) + self._partitions(rows.k, columns.k)
        # ln C(m + n - 1, n - 1) + ln m! = ln (m + n - 1)! - ln (n - 1)!
        out += self._margin(rows.size[a], rows.mass[a]).sum() + self._margin(columns.size[b], columns.mass[b]).sum()
        return float(out + self.log_f(self.m) - self.log_f(self.block).sum() + self.fixed)

    # merges -----------------------------------------------------------------

    def _pair_terms(self, block: np.ndarray) -> np.ndarray:
        """Change of the blocks' terms by merging any two rows of ``block``."""
        k = len(block)
        own = self.log_f(block).sum(axis=1)
        out = own[:, None] + own[None, :]
        for j in range(block.shape[1]):
            used = np.flatnonzero(block[:, j])
            if not len(used):
                continue
            column = block[:, j]
            f = self.log_f(column)
            # Rows without visits here keep the other's term as it is.
            out -= f[:, None] + f[None, :]
            x = column[used]
            out[np.ix_(used, used)] -= self.log_f(x[:, None] + x[None, :]) - f[used][:, None] - f[used][None, :]
        np.fill_diagonal(out, np.inf)
        return out.reshape(k, k)

    def _margin_terms(self, side: Side) -> np.ndarray:
        own = np.where(side.alive, self._margin(np.maximum(side.size, 1), side.mass), 0.0)
        both = self._margin(np.maximum(side.size[:, None] + side.size[None, :], 1), side.mass[:, None] + side.mass[None, :])
        return both - own[:, None] - own[None, :]

    def merges(self, *, stop: str = "to_null", max_rounds: int | None = None) -> list[dict]:
        """Best merge of either side, again and again; the model is left at the least cost seen.

        ``stop="first_rise"`` ends where no merge lowers the cost; ``to_null``
        goes on with the cheapest rise down to one block.
        """
        pairs = self._pairs()
        now = least = self.cost()
        best = self.rows.label.copy(), self.columns.label.copy()
        trace: list[dict] = []
        while self.rows.k * self.columns.k > 1 and (max_rounds is None or len(trace) < max_rounds):
            options = []
            for side, own in (("t", self.rows), ("s", self.columns)):
                if own.k < 2:
                    continue
                kt, ks = self.rows.k, self.columns.k
                shift = self._partitions(kt - (side == "t"), ks - (side == "s")) - self._partitions(kt, ks)
                delta = pairs[side]
                a, b = sorted(divmod(int(delta.argmin()), len(delta)))
                options.append((float(delta[a, b]) + shift, side, a, b))
            delta, side, a, b = min(options)
            if delta >= 0 and stop == "first_rise":
                break
            pair_count = sum(o.k * (o.k - 1) // 2 for o in (self.rows, self.columns))
            self._merge(side, a, b, pairs)
            self._compact(side, pairs)
            now += delta
            trace.append({"round": len(trace) + 1, "side": side, "a": a, "b": b, "delta": delta, "cost": now, "pairs": pair_count})
            if now < least - 1e-9:
                least, best = now, (self.rows.label.copy(), self.columns.label.copy())
        self.set(*best)
        return trace

    def _merge(self, side: str, a: int, b: int, pairs: dict[str, np.ndarray]) -> None:
        own, block = (self.rows, self.block) if side == "t" else (self.columns, self.block.T)
        other = pairs["s" if side == "t" else "t"]
        f = self.log_f
        # The other side's pairs lose the terms of both lines and gain those of the sum.
        x, y = block[a], block[b]
        for line, sign in ((x, 1), (y, 1), (x + y, -1)):
            used = np.flatnonzero(line)
            z, own_f = line[used], f(line)
            both = f(z[:, None] + z[None, :]) - own_f[used][:, None] - own_f[used][None, :]
            diagonal = np.diag(other).copy()
            other[np.ix_(used, used)] += sign * both
            np.fill_diagonal(other, diagonal)
        block[a] += block[b]
        block[b] = 0
        own.size[a] += own.size[b]
        own.mass[a] += own.mass[b]
        own.size[b] = own.mass[b] = 0
        own.alive[b] = False
        own.label[own.label == b] = a
        mine = pairs[side]
        used = np.flatnonzero(block[a])
        line = (f(block[a][used])[None, :] + f(block[:, used]) - f(block[a][used][None, :] + block[:, used])).sum(axis=1)
        single = np.where(own.alive, self._margin(np.maximum(own.size, 1), own.mass), 0.0)
        line += self._margin(np.maximum(own.size + own.size[a], 1), own.mass + own.mass[a]) - single - single[a]
        line[~own.alive] = np.inf
        mine[a] = mine[:, a] = line
        mine[a, a] = np.inf
        mine[b] = mine[:, b] = np.inf

    def _pairs(self) -> dict[str, np.ndarray]:
        """Change of cost by each merge of either side, but for what depends on the numbers of clusters alone."""
        return {"t": self._pair_terms(self.block) + self._margin_terms(self.rows), "s": self._pair_terms(self.block.T) + self._margin_terms(self.columns)}

    def _compact(self, side: str, pairs: dict[str, np.ndarray]) -> None:
        """Drops a side's emptied places once they are a third of all."""
        own = self.rows if side == "t" else self.columns
        keep = np.flatnonzero(own.alive)
        if len(keep) > 2 * len(own.alive) / 3 or len(keep) < 2:
            return
        place = np.full(len(own.alive), -1)
        place[keep] = np.arange(len(keep))
        own.label = place[own.label]
        own.size, own.mass, own.alive = own.size[keep], own.mass[keep], own.alive[keep]
        self.block = self.block[keep] if side == "t" else self.block[:, keep]
        pairs[side] = pairs[side][np.ix_(keep, keep)]

    # exchanges --------------------------------------------------------------

    def exchange(self, *, passes: int = 10) -> list[dict]:
        """Single vertices go to the cluster of least cost, side by side in turn, until none gains."""
        trace, now = [], self.cost()
        for p in range(passes):
            moved = 0
            for side in ("t", "s"):
                moved += self._exchange_side(side)
            then = self.cost()
            trace.append({"pass": p + 1, "moves": moved, "cost": then})
            if not moved or then > now - 1e-9:
                break
            now = then
        return trace

    def _exchange_side(self, side: str) -> int:
        own, block, other = (self.rows, self.block, self.columns) if side == "t" else (self.columns, self.block.T, self.rows)
        mine, theirs, degree = (self.t, self.s, self.row_n) if side == "t" else (self.s, self.t, self.col_n)
        order = np.argsort(mine, kind="stable")
        starts = np.searchsorted(mine[order], np.arange(len(own.label) + 1))
        f, moved = self.log_f, 0
        for v in range(len(own.label)):
            at = order[starts[v] : starts[v + 1]]
            c = int(own.label[v])
            n, d = self.n[at], int(degree[v])
            cells, where = np.unique(other.label[theirs[at]], return_inverse=True)
            add = np.bincount(where, weights=n).astype(np.int64)
            block[c, cells] -= add
            own.size[c] -= 1
            own.mass[c] -= d
            emptied = own.size[c] == 0
            own.alive[c] = not emptied
            near = block[:, cells]
            size, mass = own.size, own.mass
            delta = (f(near) - f(near + add)).sum(axis=1)
            delta += self._margin(size + 1, mass + d) - np.where(own.alive, self._margin(np.maximum(size, 1), mass), 0.0)
            k, others = own.k, other.k
            kt, ks = (k, others) if side == "t" else (others, k)
            stay = self._partitions(kt, ks)
            new = self._partitions(kt + (side == "t"), ks + (side == "s"))
            delta = delta + np.where(own.alive, stay, new)
            # One empty place stands for a cluster of its own.
            dead = np.flatnonzero(~own.alive)
            if len(dead):
                keep = c if emptied else dead[0]
                delta[dead[dead != keep]] = np.inf
            to = int(delta.argmin())
            if delta[to] >= delta[c] - 1e-9:
                to = c
            moved += to != c
            block[to, cells] += add
            own.size[to] += 1
            own.mass[to] += d
            own.alive[to] = True
            own.label[v] = to
        return moved


@dataclass
class Found:
    """A model's labels by vertex number, its cost, and how it was found."""

    rows: np.ndarray
    columns: np.ndarray
    cost: float
    trace: list[dict]


def descend(model: Model, *, stop: str = "to_null", refine: bool = True, merge: bool = True) -> Found:
    """Merges, then exchanges, then merges again while that helps."""
    trace = model.merges(stop=stop) if merge else []
    if refine:
        now = model.cost()
        while True:
            model.exchange()
            model.set(model.rows.label, model.columns.label)
            model.merges(stop=stop)
            then = model.cost()
            if then > now - 1e-6:
                break
            now = then
    return Found(model.rows.label.copy(), model.columns.label.copy(), model.cost(), trace)


def null_cost(t: np.ndarray, s: np.ndarray, n: np.ndarray, rows: int, columns: int) -> float:
    return Model(t, s, n, np.zeros(rows, dtype=int), np.zeros(columns, dtype=int)).cost()


def restart(t: np.ndarray, s: np.ndarray, n: np.ndarray, found: Found, *, seed: int, strength: int, stop: str = "to_null") -> Found:
    """One neighbour of ``found``: a share of the vertices, growing with ``strength``, goes to random clusters, some of them new."""
    rng = np.random.default_rng(seed)
    labels = []
    for label in (found.rows, found.columns):
        new, k = label.copy(), int(label.max()) + 1
        some = rng.random(len(label)) < min(1.0, 0.15 * strength)
        new[some] = rng.integers(0, k + 1 + strength, some.sum())
        labels.append(new)
    return descend(Model(t, s, n, *labels), stop=stop)
