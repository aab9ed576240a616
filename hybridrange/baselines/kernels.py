"""Baseline indices over the rows of one segment.

Every kind is built from vectors and order-keeping codes and answers
``query(q, bounds, k, omega)`` with rows, distances and costs.  They follow
general public knowledge of such structures at the published parameters.
"""

from __future__ import annotations

import heapq
from math import ceil, log2

import numpy as np

from hybridrange.kernel.stack import Found, Settings, Stack, diverse, far

#: Wide enough that one layer's window covers any segment.
WIDE = 1 << 40


def flat_stack(vecs: np.ndarray, codes: np.ndarray, m: int = 16, omega_c: int = 64, order=None, scan: bool = False) -> Stack:
    """One layer over all rows; with ``scan`` each row's candidates are the nearest before it, not those of a beam."""
    return Stack(vecs, codes, Settings(o=WIDE, m=m, omega_c=omega_c, layers=1, scan=scan)).build(order)


class Index:
    """Common state: vectors, codes and size in bytes."""

    def __init__(self, vecs: np.ndarray, codes: np.ndarray, m: int = 16, omega_c: int = 64, **more):
        self.vecs, self.codes, self.m, self.omega_c = np.asarray(vecs, float), np.asarray(codes), m, omega_c
        self.everything = (int(self.codes.min()), int(self.codes.max())) if len(self.codes) else (0, -1)
        self.prepare(**more)

    def prepare(self) -> None:
        pass

    def query(self, q: np.ndarray, bounds: tuple[int, int], k: int, omega: int) -> Found:
        raise NotImplementedError

    def bytes(self) -> int:
        return 0

    def rows_in(self, bounds: tuple[int, int]) -> np.ndarray:
        return np.flatnonzero((self.codes >= bounds[0]) & (self.codes <= bounds[1]))

    def kept(self, found: Found, bounds: tuple[int, int], k: int) -> Found:
        """Only what is in range, cut to k; every result is a filter check."""
        found.fc += len(found.rows)
        pairs = [(r, d) for r, d in zip(found.rows, found.dist, strict=True) if bounds[0] <= self.codes[r] <= bounds[1]][:k]
        found.rows, found.dist = [r for r, _ in pairs], [d for _, d in pairs]
        return found


def ranked(vecs: np.ndarray, rows: np.ndarray, q: np.ndarray, k: int) -> Found:
    d = far(vecs, rows, q) if len(rows) else np.empty(0)
    order = np.lexsort((rows, d))[:k]
    return Found(rows[order].tolist(), d[order].tolist(), len(rows))


class PreFilter(Index):
    """Filter, then scan what is left."""

    def query(self, q, bounds, k, omega):
        found = ranked(self.vecs, self.rows_in(bounds), q, k)
        found.fc = len(self.vecs)
        return found


class PostFilter(Index):
    """Search everything for as many rows as the selectivity asks for, then filter."""

    def prepare(self, alpha: float = 1.0, retry: bool = False):
        self.graph, self.alpha, self.retry = flat_stack(self.vecs, self.codes, self.m, self.omega_c), alpha, retry

    def query(self, q, bounds, k, omega):
        n, inside = len(self.vecs), len(self.rows_in(bounds))
        if not inside:
            return Found()
        fetch, dc, fc = min(n, ceil(self.alpha * k * n / inside)), 0, 0
        while True:
            found = self.graph.beam(0, q, self.everything, 0, 0, max(omega, fetch))
            found.rows, found.dist = found.rows[:fetch], found.dist[:fetch]
            found = self.kept(found, bounds, k)
            dc, fc = dc + found.dc, fc + found.fc
            if not self.retry or len(found.rows) >= min(k, inside) or fetch >= n:
                found.dc, found.fc = dc, fc
                return found
            fetch = min(n, 2 * fetch)

    def bytes(self):
        return self.graph.bytes()


class Adaptive(Index):
    """Scans or post-filters, whichever its cost model finds cheaper."""

    def prepare(self, weight: float = 2.0):
        self.graph, self.weight = PostFilter(self.vecs, self.codes, self.m, self.omega_c), weight

    def query(self, q, bounds, k, omega):
        n, inside = len(self.vecs), len(self.rows_in(bounds))
        if not inside:
            return Found()
        walk = self.weight * k * n / inside * log2(n + 1)
        return ranked(self.vecs, self.rows_in(bounds), q, k) if inside <= walk else self.graph.query(q, bounds, k, omega)

    def bytes(self):
        return self.graph.bytes()


class DenseGraph(Index):
    """Plain nearest lists of m * gamma rows without diversity, widened to two hops; only rows in range get distances."""

    def prepare(self, gamma: int = 4):
        n, m = len(self.vecs), self.m
        many = min(n - 1, m * gamma)
        self.links = []
        for i in range(n):
            d = far(self.vecs, slice(None), self.vecs[i])
            order = np.lexsort((np.arange(n), d))
            self.links.append(order[order != i][:many].tolist())

    def query(self, q, bounds, k, omega):
        inside = self.rows_in(bounds)
        if not len(inside):
            return Found()
        a, b = bounds
        start = int(inside[len(inside) // 2])
        d0 = float(far(self.vecs, [start], q)[0])
        out, seen, best, todo = Found(dc=1), {start}, [(-d0, -start)], [(d0, start)]
        while todo:
            d, here = heapq.heappop(todo)
            if len(best) >= omega and d > -best[0][0]:
                break
            fresh, met = [], set()
            for r in self.links[here]:
                for x in (r, *self.links[r][: self.m]):
                    if x in seen or x in met:
                        continue
                    met.add(x)
                    out.fc += 1
                    if a <= self.codes[x] <= b and len(fresh) < self.m:
                        seen.add(x)
                        fresh.append(x)
                if len(fresh) >= self.m:
                    break
            out.dc += len(fresh)
            for x, r in zip(far(self.vecs, fresh, q).tolist() if fresh else [], fresh, strict=True):
                if len(best) < omega or x < -best[0][0]:
                    heapq.heappush(todo, (x, r))
                    heapq.heappush(best, (-x, -r))
                    if len(best) > omega:
                        heapq.heappop(best)
        pairs = sorted((-x, -r) for x, r in best)[:k]
        out.rows, out.dist = [r for _, r in pairs], [x for x, _ in pairs]
        return out

    def bytes(self):
        return 4 * sum(map(len, self.links))


class IntervalGraph(Index):
    """One graph for all ranges: rows arrive by attribute and each link keeps the arrivals between which it was in use."""

    def prepare(self, m: int | None = None):
        m = m or self.m
        order = np.lexsort((np.arange(len(self.codes)), self.codes))
        if (np.diff(order) < 0).any():
            raise ValueError("rows have to arrive in order of their attribute")
        self.links: list[list[tuple[int, int, int]]] = [[] for _ in self.codes]
        graph, old = Stack(self.vecs, self.codes, Settings(o=WIDE, m=m, omega_c=self.omega_c, layers=1)), {}
        for row in range(len(self.codes)):
            touched = {row}
            graph.insert(row)
            touched |= set(graph.links[0][row])
            for t in touched:
                now = set(graph.links[0][t])
                for gone in set(old.get(t, {})) - now:
                    self.links[t].append((gone, old[t].pop(gone), row - 1))
                for new in now - set(old.setdefault(t, {})):
                    old[t][new] = row
        for t, alive in old.items():
            self.links[t] += [(r, born, len(self.codes)) for r, born in alive.items()]

    def query(self, q, bounds, k, omega):
        inside = self.rows_in(bounds)
        if not len(inside):
            return Found()
        first, last = int(inside[0]), int(inside[-1])
        start = int(inside[len(inside) // 2])
        d0 = float(far(self.vecs, [start], q)[0])
        out, seen, best, todo = Found(dc=1), {start}, [(-d0, -start)], [(d0, start)]
        while todo:
            d, here = heapq.heappop(todo)
            if len(best) >= omega and d > -best[0][0]:
                break
            fresh = []
            for r, born, died in self.links[here]:
                out.fc += 1
                if first <= r <= last and born <= last <= died and r not in seen:
                    seen.add(r)
                    fresh.append(r)
            out.dc += len(fresh)
            for x, r in zip(far(self.vecs, fresh, q).tolist() if fresh else [], fresh, strict=True):
                if len(best) < omega or x < -best[0][0]:
                    heapq.heappush(todo, (x, r))
                    heapq.heappush(best, (-x, -r))
                    if len(best) > omega:
                        heapq.heappop(best)
        pairs = sorted((-x, -r) for x, r in best)[:k]
        out.rows, out.dist = [r for _, r in pairs], [x for x, _ in pairs]
        return out

    def bytes(self):
        return 12 * sum(map(len, self.links))


class Blocks(Index):
    """Graphs on blocks of ranks that halve from level to level."""

    def prepare(self, least: int = 32, fanout: int = 2):
        self.order = np.lexsort((np.arange(len(self.codes)), self.codes))
        self.place = np.empty_like(self.order)
        self.place[self.order] = np.arange(len(self.order))
        self.nodes: dict[tuple[int, int], Stack] = {}
        self.spans = []
        width = len(self.order)
        while True:
            self.spans.append(width)
            for b in range(ceil(len(self.order) / width)):
                rows = self.order[b * width : (b + 1) * width]
                self.nodes[len(self.spans) - 1, b] = flat_stack(self.vecs[rows], self.codes[rows], self.m, self.omega_c, np.random.default_rng(b).permutation(len(rows)), scan=True)
            if width <= least:
                break
            width = ceil(width / fanout)

    def span(self, bounds) -> tuple[int, int] | None:
        ordered = self.codes[self.order]
        a, b = int(np.searchsorted(ordered, bounds[0], "left")), int(np.searchsorted(ordered, bounds[1], "right"))
        return (a, b) if a < b else None

    def walk(self, node: tuple[int, int], q, bounds, omega: int) -> Found:
        graph, rows = self.nodes[node], self.order[node[1] * self.spans[node[0]] : (node[1] + 1) * self.spans[node[0]]]
        inside = np.flatnonzero((graph.codes >= bounds[0]) & (graph.codes <= bounds[1]))
        if not len(inside):
            return Found()
        found = graph.beam(int(inside[len(inside) // 2]), q, bounds, 0, 0, omega)
        found.rows = [int(rows[r]) for r in found.rows]
        return found

    def bytes(self):
        return sum(x.bytes() for x in self.nodes.values())


class BlockSuperset(Blocks):
    """The smallest block that holds the range, or two neighbours, searched without the range and filtered afterwards."""

    def prepare(self, mult: int = 3, **more):
        super().prepare(**more)
        self.mult = mult

    def query(self, q, bounds, k, omega):
        if not (span := self.span(bounds)):
            return Found()
        for level in range(len(self.spans) - 1, -1, -1):
            first, last = span[0] // self.spans[level], (span[1] - 1) // self.spans[level]
            if last - first <= (0 if level == 0 else 1):
                break
        parts = []
        for b in range(first, last + 1):
            graph = self.nodes[level, b]
            whole = (int(graph.codes.min()), int(graph.codes.max()))
            parts.append(self.kept(self.walk((level, b), q, whole, max(omega, self.mult * k)), bounds, k))
        return merged(parts, k)


class BlockEdges(Blocks):
    """A list per level of blocks; each hop takes links in range from the highest block down until it has enough."""

    def query(self, q, bounds, k, omega):
        if not (span := self.span(bounds)):
            return Found()
        start = int(self.order[(span[0] + span[1] - 1) // 2])
        d0 = float(far(self.vecs, [start], q)[0])
        out, seen, best, todo = Found(dc=1), {start}, [(-d0, -start)], [(d0, start)]
        while todo:
            d, here = heapq.heappop(todo)
            if len(best) >= omega and d > -best[0][0]:
                break
            fresh, at = [], int(self.place[here])
            for level, width in enumerate(self.spans):
                b = at // width
                for r in self.nodes[level, b].links[0][at - b * width]:
                    row = int(self.order[b * width + r])
                    out.fc += 1
                    if bounds[0] <= self.codes[row] <= bounds[1] and row not in seen and len(fresh) < self.m:
                        seen.add(row)
                        fresh.append(row)
                if len(fresh) >= self.m or span[0] <= b * width and (b + 1) * width <= span[1]:
                    break
            out.dc += len(fresh)
            for x, r in zip(far(self.vecs, fresh, q).tolist() if fresh else [], fresh, strict=True):
                if len(best) < omega or x < -best[0][0]:
                    heapq.heappush(todo, (x, r))
                    heapq.heappush(best, (-x, -r))
                    if len(best) > omega:
                        heapq.heappop(best)
        pairs = sorted((-x, -r) for x, r in best)[:k]
        out.rows, out.dist = [r for _, r in pairs], [x for x, _ in pairs]
        return out


def merged(parts: list[Found], k: int) -> Found:
    pairs = sorted((d, r) for p in parts for r, d in zip(p.rows, p.dist, strict=True))[:k]
    return Found([r for _, r in pairs], [d for d, _ in pairs], sum(p.dc for p in parts), sum(p.fc for p in parts))


class Node:
    """A tree node: its rows in a flat graph over all vectors, and its children in order of their codes."""

    def __init__(self, tree: MultiwayTree, rows: list[int], children: list[Node] | None = None):
        self.rows, self.children, self.tree = list(rows), children or [], tree
        self.graph = Stack(tree.vecs, tree.codes, Settings(o=WIDE, m=tree.m, omega_c=tree.omega_c, layers=1))
        for r in np.random.default_rng(len(rows)).permutation(len(rows)).tolist():
            self.graph.insert(rows[r])
        self.low = min((int(tree.codes[r]) for r in rows), default=0)
        self.high = max((int(tree.codes[r]) for r in rows), default=-1)


class MultiwayTree(Index):
    """Graphs on the nodes of a tree of large fan-out; the fewest nodes that cover the range are searched and merged.

    ``first`` is the share of the rows that are loaded at once; the others are
    inserted one by one into the graphs on their way down.  A leaf of twice
    ``least`` rows and a node of more than ``fanout`` children are split in two.
    """

    def prepare(self, fanout: int = 8, least: int = 64, first: float = 1.0):
        self.fanout, self.least = fanout, least
        n = max(1, round(first * len(self.codes)))
        self.root = self.loaded(sorted(range(n), key=lambda r: (int(self.codes[r]), r)))
        for row in range(n, len(self.codes)):
            if more := self.put(self.root, row):
                self.root = Node(self, self.root.rows + more.rows, [self.root, more])

    def loaded(self, rows: list[int]) -> Node:
        """A balanced tree over rows in order; equal codes stay in one child."""
        if len(rows) <= self.least:
            return Node(self, rows)
        ends = [len(rows) * i // self.fanout for i in range(1, self.fanout)]
        ends = sorted({e for e in ends if self.codes[rows[e]] != self.codes[rows[e - 1]]})
        parts = [rows[a:b] for a, b in zip([0, *ends], [*ends, len(rows)], strict=True)]
        return Node(self, rows, [self.loaded(x) for x in parts] if len(parts) > 1 else None)

    def put(self, node: Node, row: int) -> Node | None:
        """Inserts a row below a node; a new right neighbour of the node if that is split."""
        code = int(self.codes[row])
        node.graph.insert(row)
        node.rows.append(row)
        node.low, node.high = min(node.low, code), max(node.high, code)
        if node.children:
            at = max(0, sum(x.low <= code for x in node.children) - 1)
            if more := self.put(node.children[at], row):
                node.children.insert(at + 1, more)
            if len(node.children) <= self.fanout:
                return None
            half = len(node.children) // 2
            left, right = node.children[:half], node.children[half:]
        else:
            ordered = sorted(node.rows, key=lambda r: (int(self.codes[r]), r))
            half = len(ordered) // 2
            while half < len(ordered) and self.codes[ordered[half]] == self.codes[ordered[half - 1]]:
                half += 1
            if len(ordered) < 2 * self.least or half == len(ordered):
                return None
            left, right = ordered[:half], ordered[half:]
        parts = [Node(self, [r for x in p for r in x.rows], p) if node.children else Node(self, p) for p in (left, right)]
        node.__dict__.update(parts[0].__dict__)
        return parts[1]

    def cover(self, node: Node, bounds: tuple[int, int]) -> list[Node]:
        if node.high < bounds[0] or node.low > bounds[1]:
            return []
        if not node.children or bounds[0] <= node.low and node.high <= bounds[1]:
            return [node]
        return [y for x in node.children for y in self.cover(x, bounds)]

    def query(self, q, bounds, k, omega):
        parts = []
        for node in self.cover(self.root, bounds):
            inside = sorted((int(self.codes[r]), r) for r in node.rows if bounds[0] <= self.codes[r] <= bounds[1])
            if inside:
                parts.append(node.graph.beam(inside[len(inside) // 2][1], q, bounds, 0, 0, omega))
        return merged(parts, k)

    def bytes(self):
        def size(node: Node) -> int:
            return node.graph.bytes() + sum(map(size, node.children))

        return size(self.root)


class Slots(Index):
    """The attribute in equal slots; each row keeps diverse neighbours for every slot and walks those that the range meets."""

    def prepare(self, slots: int = 8):
        order = np.lexsort((np.arange(len(self.codes)), self.codes))
        self.slot = np.empty(len(order), int)
        self.slot[order] = np.arange(len(order)) * slots // max(1, len(order))
        per, self.links = max(2, self.m // 2), []
        groups = [np.flatnonzero(self.slot == s) for s in range(slots)]
        for i in range(len(self.codes)):
            own = []
            for rows in groups:
                rows = rows[rows != i]
                d = far(self.vecs, rows, self.vecs[i]) if len(rows) else np.empty(0)
                near = np.lexsort((rows, d))[: self.omega_c]
                own.append(diverse(self.vecs, d[near].tolist(), rows[near].tolist(), per))
            self.links.append(own)

    def query(self, q, bounds, k, omega):
        inside = self.rows_in(bounds)
        if not len(inside):
            return Found()
        met = range(int(self.slot[inside].min()), int(self.slot[inside].max()) + 1)
        ordered = inside[np.lexsort((inside, self.codes[inside]))]
        start = int(ordered[len(ordered) // 2])
        d0 = float(far(self.vecs, [start], q)[0])
        out, seen, best, todo = Found(dc=1), {start}, [(-d0, -start)], [(d0, start)]
        while todo:
            d, here = heapq.heappop(todo)
            if len(best) >= omega and d > -best[0][0]:
                break
            fresh = []
            for s in met:
                for r in self.links[here][s]:
                    out.fc += 1
                    if r not in seen and bounds[0] <= self.codes[r] <= bounds[1]:
                        seen.add(r)
                        fresh.append(r)
            out.dc += len(fresh)
            for x, r in zip(far(self.vecs, fresh, q).tolist() if fresh else [], fresh, strict=True):
                if len(best) < omega or x < -best[0][0]:
                    heapq.heappush(todo, (x, r))
                    heapq.heappush(best, (-x, -r))
                    if len(best) > omega:
                        heapq.heappop(best)
        pairs = sorted((-x, -r) for x, r in best)[:k]
        out.rows, out.dist = [r for _, r in pairs], [x for x, _ in pairs]
        return out

    def bytes(self):
        return 4 * sum(len(s) for x in self.links for s in x)


def centres(x: np.ndarray, n: int, rounds: int = 8, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Plain k-means: centres and the nearest one of each row."""
    c = x[np.random.default_rng(seed).choice(len(x), min(n, len(x)), replace=False)].copy()
    near = np.zeros(len(x), int)
    for _ in range(rounds):
        near = ((x**2).sum(1)[:, None] - 2 * x @ c.T + (c**2).sum(1)).argmin(1)
        for j in range(len(c)):
            if (near == j).any():
                c[j] = x[near == j].mean(0)
    return c, near


class CodedTree(Index):
    """Product-quantised codes in attribute order: table distances pick a base list in range, exact distances rank it.

    The list holds ``share`` of the rows in range, at least ``least`` and the
    beam's width.  Books are learnt from the ``first`` share of the rows; rows that
    arrive later take the nearest words and change no book.
    """

    def prepare(self, parts: int = 16, words: int = 64, share: float = 0.1, least: int = 50, first: float = 1.0):
        self.cut = np.array_split(np.arange(self.vecs.shape[1]), parts)
        n = max(1, round(first * len(self.vecs)))
        self.books = []
        for c in self.cut:
            x = self.vecs[:, c]
            words_, _ = centres(x[:n], words)
            self.books.append((words_, ((x**2).sum(1)[:, None] - 2 * x @ words_.T + (words_**2).sum(1)).argmin(1)))
        self.share, self.least = share, least

    def query(self, q, bounds, k, omega):
        rows = self.rows_in(bounds)
        if not len(rows):
            return Found()
        table = sum((((c - q[cols]) ** 2).sum(1))[near[rows]] for (c, near), cols in zip(self.books, self.cut, strict=True))
        chosen = rows[np.lexsort((rows, table))[: max(k, omega, self.least, int(self.share * len(rows)))]]
        found = ranked(self.vecs, chosen, q, k)
        found.fc = len(rows)
        return found

    def bytes(self):
        return len(self.vecs) * len(self.cut) + 8 * sum(c.size for c, _ in self.books)


class Partitions(Index):
    """Lists around centres; the nearest lists are scanned for rows in range."""

    def prepare(self, lists: int | None = None, probe: int = 8):
        self.c, self.near = centres(self.vecs, lists or max(1, int(len(self.vecs) ** 0.5)))
        self.probe = probe

    def query(self, q, bounds, k, omega):
        order = ((self.c - q) ** 2).sum(1).argsort(kind="stable")[: self.probe]
        rows = np.flatnonzero(np.isin(self.near, order))
        found = ranked(self.vecs, rows[(self.codes[rows] >= bounds[0]) & (self.codes[rows] <= bounds[1])], q, k)
        found.fc, found.dc = len(rows), found.dc + len(self.c)
        return found

    def bytes(self):
        return 4 * len(self.vecs) + 8 * self.c.size


class Hashed(Index):
    """Several tables of random projections; rows in a query's buckets and in range are ranked."""

    def prepare(self, tables: int = 16, bits: int = 4, seed: int = 5):
        self.planes = np.random.default_rng(seed).normal(size=(tables, bits, self.vecs.shape[1]))
        self.keys = self.key(self.vecs)

    def key(self, x: np.ndarray) -> np.ndarray:
        signs = np.einsum("tbd,nd->ntb", self.planes, np.atleast_2d(x)) > 0
        return (signs * (1 << np.arange(signs.shape[2]))).sum(2)

    def query(self, q, bounds, k, omega):
        rows = np.flatnonzero((self.keys == self.key(q)).any(1))
        found = ranked(self.vecs, rows[(self.codes[rows] >= bounds[0]) & (self.codes[rows] <= bounds[1])], q, k)
        found.fc = len(rows)
        return found

    def bytes(self):
        return 4 * self.keys.size


class OracleGraph(Index):
    """A flat graph built on just the rows of each query's range: the bound for distance computations.

    The graph of all rows and the last one are kept, as many ranges cover a segment
    and a sweep asks the same range at every width.
    """

    def prepare(self):
        self.kept_graphs = {}

    def graph_of(self, rows: np.ndarray, bounds: tuple[int, int]) -> Stack:
        if bounds not in self.kept_graphs:
            self.kept_graphs = {b: g for b, g in self.kept_graphs.items() if b == self.everything}
            self.kept_graphs[bounds] = flat_stack(self.vecs[rows], self.codes[rows], self.m, self.omega_c, scan=True)
        return self.kept_graphs[bounds]

    def query(self, q, bounds, k, omega):
        rows = self.rows_in(bounds)
        if not len(rows):
            return Found()
        graph = self.graph_of(rows, bounds)
        middle = int(np.lexsort((rows, self.codes[rows]))[len(rows) // 2])
        found = graph.beam(middle, q, self.everything, 0, 0, max(omega, k))
        found.rows, found.dist = [int(rows[r]) for r in found.rows[:k]], found.dist[:k]
        return found


class WindowStack(Index):
    """The window stack under the common interface."""

    def prepare(self, how: dict | None = None, **settings):
        self.how = {"complete": False} | (how or {})
        self.stack = Stack(self.vecs, self.codes, Settings(m=self.m, omega_c=self.omega_c, **settings)).build()

    def query(self, q, bounds, k, omega):
        return self.stack.query(q, bounds, k, omega, **self.how)

    def bytes(self):
        return self.stack.bytes()


KINDS: dict[str, type[Index]] = {
    "prefilter": PreFilter, "flat_graph": PostFilter, "adaptive": Adaptive, "dense_graph": DenseGraph, "interval_graph": IntervalGraph, "block_tree_superset": BlockSuperset,
    "block_tree_edges": BlockEdges, "slot_graph": Slots, "pq_tree": CodedTree, "multiway_tree": MultiwayTree, "oracle_graph": OracleGraph, "ivf": Partitions, "lsh": Hashed, "window_stack": WindowStack,
}
