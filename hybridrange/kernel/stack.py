"""The window stack inside one segment: insertion, beam search and range queries.

Rows are numbered in order of arrival and carry an integer code of their
attribute that keeps its order.  Layer l links rows whose unique values are at
most o**l ranks apart; searching starts from the layer that fits the range and
looks further down, hop by hop, only where the range turned a neighbour away.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np

from hybridrange.kernel.ordertree import SortedArray, WeightBalancedTree
from hybridrange.layers import landing_layer


@dataclass
class Settings:
    """``o``: window base, ``m``: most links, ``omega_c``: beam width while building; the rest switch variants."""

    o: int = 4
    m: int = 16
    omega_c: int = 64
    carry_over: bool = True
    lazy: bool = True
    diverse: bool = True
    strict: bool = False
    tree: bool = False
    layers: int | None = None  # a fixed number of layers instead of a growing one; 1 and a wide base make a flat graph
    scan: bool = False  # an insertion that takes all distances at once takes the nearest rows from them, in place of a beam
    seed: int = 11


@dataclass
class Found:
    """Rows by distance, with distance computations (dc), filter checks (fc) and the layers each hop saw."""

    rows: list[int] = field(default_factory=list)
    dist: list[float] = field(default_factory=list)
    dc: int = 0
    fc: int = 0
    hops: list[tuple[int, int]] = field(default_factory=list)
    in_range: list[int] = field(default_factory=lambda: [0, 0])
    scanned: bool = False


def far(vecs: np.ndarray, rows, q: np.ndarray) -> np.ndarray:
    d = vecs[rows] - q
    return np.sqrt(np.einsum("ij,ij->i", d, d))


#: Candidates beyond twice the cap among which a first look is taken for those to keep.
FIRST = 8


def diverse(vecs: np.ndarray, dist: list[float], rows: list[int], cap: int, prune: bool = True) -> list[int]:
    """Of rows in order of distance to a target, those not nearer to a kept row than to the target, up to ``cap``."""
    if not prune or len(rows) < 2:
        return rows[:cap]
    some = 2 * cap + FIRST
    if len(rows) > some:  # the nearest mostly fill the cap, and what follows bars none of them
        kept = diverse(vecs, dist[:some], rows[:some], cap)
        if len(kept) == cap:
            return kept
    x, d = vecs[rows], np.asarray(dist)
    size = np.einsum("ij,ij->i", x, x)
    # every distance between two candidates at once; what rounding leaves below zero is a copy
    near = np.sqrt(np.maximum(size[:, None] + size[None, :] - 2 * (x @ x.T), 0)) < d[None, :] * (1 - 1e-12)
    # a row's bits are the candidates that it bars
    bits, wide = np.packbits(near, axis=1, bitorder="little").tobytes(), -(-len(rows) // 8)
    barred, kept = 0, []
    for i, r in enumerate(rows):
        if not barred >> i & 1:
            kept.append(r)
            if len(kept) == cap:
                break
            barred |= int.from_bytes(bits[i * wide : i * wide + wide], "little")
    return kept


#: Rows of a stack up to which an insertion takes all its distances at once.
AT_ONCE = 8_192
#: The same for a query, which meets fewer of them; they count only where they are met.
AT_ONCE_QUERY = 1_024
#: Rows beyond which a build in order of arrival scans windows of few rows, of which a beam would meet about as many.
LARGE = 2_048
#: Distances in a block, and rows up to which such a build takes them in blocks, with windows of AT_ONCE rows scanned and else of AT_ONCE_QUERY.
BLOCK, MOST = 1 << 23, 1 << 17


class Ahead:
    """What a build in order of arrival knows of its rows before they arrive: their places by code, and distances by blocks."""

    def __init__(self, vecs: np.ndarray, codes: np.ndarray):
        self.vecs, self.size = vecs, np.einsum("ij,ij->i", vecs, vecs)
        self.rows = np.lexsort((np.arange(len(codes)), codes))
        self.codes, self.place = codes[self.rows], np.argsort(self.rows)
        self.here = np.zeros(len(codes), bool)
        self.first, self.block = 0, np.empty((0, 0))
        # a product rounds distances of near copies, which are taken again
        self.rounded = (1e-3 * np.sqrt(self.size)).tolist()

    def arrived(self, row: int) -> None:
        self.here[self.place[row]] = True

    def distances(self, row: int) -> np.ndarray | None:
        """Of a row to all before it, by one product for a block of rows; None with too many rows for that."""
        if len(self.vecs) > MOST:
            return None
        if not self.first <= row < self.first + len(self.block):
            to = min(len(self.vecs), row + max(1, BLOCK // len(self.vecs)))
            d = self.vecs[row:to] @ self.vecs[:to].T
            d *= -2
            d += self.size[row:to, None]
            d += self.size[None, :to]
            self.first, self.block = row, np.sqrt(np.maximum(d, 0, out=d), out=d)
        return self.block[row - self.first]

    def nearest(self, bounds: tuple[int, int], row: int, dist: np.ndarray | None, omega: int) -> Found | None:
        """The ``omega`` rows nearest to ``row`` of those that are there within ``bounds``; None if these are too many to scan."""
        a, b = np.searchsorted(self.codes, bounds[0], "left"), np.searchsorted(self.codes, bounds[1], "right")
        if np.count_nonzero(self.here[a:b]) > (AT_ONCE_QUERY if dist is None else AT_ONCE):
            return None
        rows = self.rows[a:b][self.here[a:b]]
        d = far(self.vecs, rows, self.vecs[row]) if dist is None else dist[rows]
        if len(rows) > omega:
            near = d <= np.partition(d, omega - 1)[omega - 1]
            rows, d = rows[near], d[near]
        order = np.lexsort((rows, d))[:omega]
        return Found(rows[order].tolist(), d[order].tolist(), len(d))


class Stack:
    def __init__(self, vecs: np.ndarray, codes: np.ndarray, settings: Settings | None = None):
        self.s = settings or Settings()
        self.vecs, self.codes = np.asarray(vecs, float), np.asarray(codes)
        self.values = WeightBalancedTree() if self.s.tree else SortedArray()
        self.links: list[list[list[int]]] = [[] for _ in range(self.s.layers or 1)]
        self.at_value: dict[int, list[int]] = {}
        self.deleted, self.there = np.zeros(len(self.vecs), bool), np.zeros(len(self.vecs), bool)
        self.count = 0
        self.code_of: list[int] = self.codes.tolist()
        self.ordered: tuple[tuple, np.ndarray] | None = None
        self.ahead: Ahead | None = None

    @property
    def top(self) -> int:
        return len(self.links) - 1

    def window(self, code: int, layer: int) -> tuple[int, int] | None:
        """First and last value at most o**layer ranks from ``code`` among those inserted."""
        n, reach = len(self.values), self.s.o ** (layer if self.s.layers is None else 1) - self.s.strict
        if not n:
            return None
        rank, there = self.values.rank(code), code in self.values
        low, high = max(0, rank - reach), min(n - 1, rank + reach - (not there))
        return (self.values.select(low), self.values.select(high)) if low <= high else None

    def entry(self, bounds: tuple[int, int], turn: int) -> int:
        """A row in the window, drawn by a seeded hash."""
        a, b = self.values.rank(bounds[0]), self.values.rank(bounds[1])
        x = (turn * 2654435761 + self.s.seed * 40503) % 2**32
        rows = self.at_value[self.values.select(a + x % (b - a + 1))]
        return rows[x // 7 % len(rows)]

    def insert(self, row: int) -> None:
        s, code, q = self.s, int(self.codes[row]), self.vecs[row]
        # a strict layer 0 links nothing, so without the second term the first rows would start parts that never meet
        while s.layers is None and len(self.values) + (code not in self.values) > 2 * (s.o**self.top - s.strict):
            self.links.append([list(x) for x in self.links[-1]])
        for layer in self.links:
            while len(layer) <= row:
                layer.append([])
        pool: dict[int, float] = {}
        ahead = self.ahead
        dist = far(self.vecs, slice(0, len(self.links[0])), q) if len(self.links[0]) <= AT_ONCE and not ahead else None
        known = ahead.distances(row) if ahead else None if dist is None or s.scan else dist.tolist()
        for l in range(self.top, -1, -1):
            bounds = self.window(code, l)
            if bounds is None:
                continue
            pool = {r: d for r, d in pool.items() if bounds[0] <= self.code_of[r] <= bounds[1]}
            if not (s.carry_over and len(pool) > s.m):
                found = ahead.nearest(bounds, row, known, s.omega_c) if ahead else self.nearest(dist, bounds, s.omega_c) if s.scan and dist is not None else None
                if found is None:
                    found = self.beam(self.entry(bounds, row + l), q, bounds, l, self.top, s.omega_c, skip=row, known=known)
                if ahead and known is not None and found.rows and found.dist[0] < ahead.rounded[row]:
                    found.dist = far(self.vecs, found.rows, q).tolist()
                pool |= dict(zip(found.rows, found.dist, strict=True))
            near = sorted(pool, key=lambda r: (pool[r], r))
            chosen = diverse(self.vecs, [pool[r] for r in near], near, s.m // 2, s.diverse)
            self.links[l][row] = chosen
            for b in chosen:
                self.link_back(l, b, row, pool[b])
        self.values.insert(code)
        self.at_value.setdefault(code, []).append(row)
        self.there[row] = True
        self.count += 1
        if self.ahead:
            self.ahead.arrived(row)

    def nearest(self, dist: np.ndarray, bounds: tuple[int, int], omega: int) -> Found:
        """The ``omega`` nearest of the inserted rows within ``bounds``; ``dist`` has all their distances."""
        n = len(dist)
        rows = np.flatnonzero(self.there[:n] & ~self.deleted[:n] & (self.codes[:n] >= bounds[0]) & (self.codes[:n] <= bounds[1]))
        rows = rows[np.lexsort((rows, dist[rows]))[:omega]]
        return Found(rows.tolist(), dist[rows].tolist(), len(rows))

    def link_back(self, l: int, b: int, row: int, dist: float) -> None:
        mine, s = self.links[l][b], self.s
        if len(mine) < s.m and s.lazy:
            mine.append(row)
            return
        bounds = self.window(int(self.codes[b]), l)
        rest = [r for r in mine if bounds[0] <= self.code_of[r] <= bounds[1] and not self.deleted[r]]
        if len(rest) < s.m and not s.lazy:
            self.links[l][b] = [*rest, row]
            return
        d = {r: x for r, x in zip(rest, far(self.vecs, rest, self.vecs[b]).tolist() if rest else [], strict=True)} | {row: dist}
        near = sorted(d, key=lambda r: (d[r], r))
        self.links[l][b] = diverse(self.vecs, [d[r] for r in near], near, s.m, s.diverse)

    def build(self, order=None) -> Stack:
        if order is None and len(self.vecs) > LARGE:
            self.ahead = Ahead(self.vecs, self.codes)
        for row in range(len(self.vecs)) if order is None else order:
            self.insert(int(row))
        self.ahead = None  # what comes later is not among its rows
        return self

    def beam(self, entry: int, q: np.ndarray, bounds: tuple[int, int], low: int, high: int, omega: int, early_stop: bool = True, budget: int | None = None, trace: bool = False, skip: int = -1, known: list[float] | np.ndarray | None = None, hidden: np.ndarray | None = None) -> Found:
        """Nearest rows within ``bounds``, at most ``omega``, over layers ``high`` down to ``low``.

        Never ``skip``, a row that is being linked; ``known`` holds distances that
        were taken before; ``hidden`` rows are walked and not returned, as deleted
        ones are.  A hop takes at most ``budget`` new rows, ``m`` if not given.
        """
        budget, codes, links = budget or self.s.m, self.code_of, self.links
        deleted = self.deleted if hidden is None else self.deleted | hidden
        gone = bool(deleted.any())
        a, b = bounds
        block, known = (known, None) if isinstance(known, np.ndarray) else (None, known)
        if block is None and known is None and len(links[0]) <= AT_ONCE_QUERY:
            known = far(self.vecs, slice(0, len(links[0])), q).tolist()
        push, pop, swap = heapq.heappush, heapq.heappop, heapq.heappushpop
        seen = {entry, skip}
        d0 = known[entry] if known else float(far(self.vecs, [entry], q)[0] if block is None else block[entry])
        out, best, todo = Found(), [], [(d0, entry)]
        if not deleted[entry]:
            best.append((-d0, -entry))
        full = len(best) >= omega
        dc, fc, met, inside = 1, 0, 0, 0
        while todo:
            d, here = pop(todo)
            if full and d > -best[0][0]:
                break
            fresh: list[int] = []
            l, deeper = high, True
            while l >= low and deeper:
                new = [r for r in links[l][here] if r not in seen]
                mine = [r for r in new if a <= codes[r] <= b]
                fc += len(new)
                if l == high:
                    met += len(new)
                    inside += len(mine)
                deeper = not early_stop or len(mine) < len(new)
                if mine and len(fresh) < budget:
                    mine = mine[: budget - len(fresh)]
                    seen.update(mine)
                    fresh += mine
                l -= 1
            if trace:
                out.hops.append((l + 1, high))
            if fresh:
                dc += len(fresh)
                for x, r in zip([known[r] for r in fresh] if known else (far(self.vecs, fresh, q) if block is None else block[fresh]).tolist(), fresh, strict=True):
                    if full and not x < -best[0][0]:
                        continue
                    push(todo, (x, r))
                    if gone and deleted[r]:
                        continue
                    if full:
                        swap(best, (-x, -r))
                    else:
                        push(best, (-x, -r))
                        full = len(best) >= omega
        out.dc, out.fc, out.in_range = dc, fc, [inside, met]
        ranked = sorted((-x, -r) for x, r in best)
        out.rows, out.dist = [r for _, r in ranked], [x for x, _ in ranked]
        return out

    def sorted_rows(self) -> tuple[np.ndarray, np.ndarray]:
        """Codes in order and their rows, renewed when rows have arrived."""
        if self.ordered is None or self.ordered[0] != self.count:
            c = self.codes[: len(self.links[0])]
            order = np.lexsort((np.arange(len(c)), c))
            self.ordered = (self.count, (c[order], order))
        return self.ordered[1]

    def in_range(self, bounds: tuple[int, int]) -> np.ndarray:
        codes, rows = self.sorted_rows()
        a, b = np.searchsorted(codes, bounds[0], "left"), np.searchsorted(codes, bounds[1], "right")
        return rows[a:b]

    def scan(self, q: np.ndarray, bounds: tuple[int, int], k: int, hidden: np.ndarray | None = None) -> Found:
        rows = self.in_range(bounds)
        rows = rows[~(self.deleted[rows] if hidden is None else self.deleted[rows] | hidden[rows])]
        d = far(self.vecs, rows, q) if len(rows) else np.empty(0)
        order = np.lexsort((rows, d))[:k]
        return Found(rows[order].tolist(), d[order].tolist(), len(rows), 0, scanned=True)

    def landing(self, bounds: tuple[int, int], inside: int, how: int | str) -> int:
        """The layer to start from: the one that fits the range, the top, a given one, or the one that fits an estimate from 64 cut points."""
        if how == "top":
            return self.top
        if isinstance(how, int):
            return max(0, min(how, self.top))
        if how == "estimate":
            n = len(self.values)
            cuts = [self.values.select(i * (n - 1) // 64) for i in range(65)]
            inside = max(1, sum(bounds[0] <= c <= bounds[1] for c in cuts) * n // 65)
        return landing_layer(inside, self.s.o, self.top)

    def query(self, q: np.ndarray, bounds: tuple[int, int], k: int = 10, omega: int = 64, early_stop: bool = True, landing: int | str = "auto", scan_cap: int = 0, trace: bool = False, complete: bool = True, budget: int | None = None, hidden: np.ndarray | None = None) -> Found:
        """The k nearest rows within closed bounds.

        A range of at most ``scan_cap`` rows is scanned.  With ``complete``, an
        addition to the published method that the experiments switch off, so is one
        of which the beam returns fewer rows than it holds, up to k; the result says
        whether it was ``scanned``.
        """
        inside = self.values.count(*bounds)
        if inside <= 0:
            return Found()
        codes, _ = self.sorted_rows()
        n = int(np.searchsorted(codes, bounds[1], "right") - np.searchsorted(codes, bounds[0], "left"))
        if n <= scan_cap:
            return self.scan(q, bounds, k, hidden)
        middle = self.values.select(self.values.rank(bounds[0]) + (inside - 1) // 2)
        found = self.beam(self.at_value[middle][0], np.asarray(q, float), bounds, 0, self.landing(bounds, inside, landing), max(omega, k), early_stop, budget, trace, hidden=hidden)
        if complete and len(found.rows) < min(k, n):
            again = self.scan(q, bounds, k, hidden)
            if len(again.rows) > len(found.rows):
                again.dc += found.dc
                again.fc, again.hops = found.fc, found.hops
                return again
        found.rows, found.dist = found.rows[:k], found.dist[:k]
        return found

    def bytes(self) -> int:
        """Published size rule: every layer has m slots of four bytes for every row."""
        return self.count * len(self.links) * self.s.m * 4
