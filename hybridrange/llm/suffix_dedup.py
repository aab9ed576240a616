"""Suffix-array dedup: removes every byte under a string of LENGTH bytes that starts elsewhere too.

A suffix array over everything would carry LENGTH bytes a suffix, so the sort is
dealt out by content.  Minima of k-gram hashes over every LENGTH-long string
mark anchors: two equal strings hold an anchor at the same place, hence the
bytes around equal anchors (contexts) hold all repeats.  Equal contexts are
folded first.  Contexts that differ meet under the hash of the part that a
string to the left, or to the right, of the anchor must cover.  There each is trimmed to
what it shares with its neighbours in order, equal ones are folded, and a suffix
array decides: only suffixes smaller than their successors are sorted directly,
the rest is induced by scans over the buckets of first bytes, and adjacent common
prefixes of LENGTH bytes mark repeats.  The strings of groups beyond GROUP
contexts are settled by exact counts instead.

Passages of over PASSAGE words may be shorter than LENGTH bytes, so documents
that share one with another document are marked beside: every string of PASSAGE
words holds a least gram of words, whose surroundings are compared by blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

LENGTH = 400
GRAM = 32
#: Contexts of one key that one task takes; beyond, every string is counted.
GROUP = 150_000
#: Bytes that are sorted at once; a group with more distinct bytes is counted in the task.
BATCH, MOST = 600_000, 2_000_000
#: Words of a passage; words of the grams that anchor it, of a block beside, and blocks of each side that are compared.
PASSAGE, WORDS, STEP = 50, 8, 7
#: Blocks of both sides together that a string of more than PASSAGE words around its anchor is sure to cover.
SIDE = COVERED = -(-(PASSAGE + 1 - WORDS - 2 * (STEP - 1)) // STEP)
_BASE, _INVERSE = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 2**64)
_POWERS: dict[str, np.ndarray] = {}
_WHITE = np.zeros(256, bool)
_WHITE[list(C.WHITE)] = True


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if "up" not in _POWERS or len(_POWERS["up"]) < n:
        n = max(n, 1 << 16)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            x = np.full(n, base, np.uint64)
            x[0] = 1
            with np.errstate(over="ignore"):
                _POWERS[name] = np.cumprod(x)
    return _POWERS["up"], _POWERS["down"]


def prefix_sums(b: np.ndarray) -> np.ndarray:
    """Sums of powers modulo 2**64 before each place, by which any part of ``b`` is hashed."""
    up, sums = powers(len(b) + 1)[0], np.zeros(len(b) + 1, np.uint64)
    x = b.astype(np.uint64)
    with np.errstate(over="ignore"):
        x += np.uint64(1)
        x *= up[: len(b)]
        np.cumsum(x, out=sums[1:])
    return sums


def mixed(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xD6E8FEB86659FD93)
        h ^= h >> np.uint64(29)
    return h


def gram_hashes(b: np.ndarray, k: int = GRAM, sums: np.ndarray | None = None) -> np.ndarray:
    """A hash of every k-gram by prefix sums of powers modulo 2**64."""
    sums = prefix_sums(b) if sums is None else sums
    with np.errstate(over="ignore"):
        return mixed((sums[k:] - sums[:-k]) * powers(len(b) + 1)[1][: max(0, len(b) - k + 1)])


def word_hashes(text: bytes) -> np.ndarray:
    """A hash of every run of bytes other than white space, in order."""
    b = np.frombuffer(text, np.uint8)
    white = np.ones(len(b) + 2, bool)
    white[1:-1] = _WHITE[b]
    edge, sums = np.flatnonzero(white[1:] != white[:-1]), prefix_sums(b)
    first, end = edge[::2], edge[1::2]
    with np.errstate(over="ignore"):
        return mixed((sums[end] - sums[first]) * powers(len(b) + 1)[1][first])


def sliding(x: np.ndarray, w: int, op=np.minimum) -> np.ndarray:
    """op over every w neighbours, by running values of blocks of w."""
    fill = np.full(-len(x) % w, np.iinfo(x.dtype).max if op is np.minimum else np.iinfo(x.dtype).min, x.dtype)
    rows = np.concatenate([x, fill]).reshape(-1, w)
    ahead = op.accumulate(rows, 1).reshape(-1)
    behind = op.accumulate(rows[:, ::-1], 1)[:, ::-1].reshape(-1)
    n = len(x) - w + 1
    return op(behind[:n], ahead[w - 1 : w - 1 + n])


def anchors(text: bytes, length: int = LENGTH) -> np.ndarray:
    """Rows of (p, a, b): places p of the least k-gram hash of some string of ``length`` bytes, and the starts a..b of the strings judged there.

    Each string is judged at its leftmost least place.  Where hashes tie, it may
    be judged at others too.
    """
    if len(text) < length:
        return np.empty((0, 3), np.int64)
    h, w = gram_hashes(np.frombuffer(text, np.uint8)), length - GRAM + 1
    least = sliding(h, w)
    pad = np.zeros(w - 1, np.uint64)
    found = np.flatnonzero(sliding(np.concatenate([pad, least, pad]), w, np.maximum) == h)
    starts = np.concatenate([[0], np.flatnonzero(least[1:] != least[:-1]) + 1])
    if len(starts) == len(found):  # one place for each run of equal minima, in the same order
        return np.stack([found, starts, np.append(starts[1:] - 1, len(least) - 1)], 1)
    return np.stack([found, np.maximum(0, found - w + 1), np.minimum(found, len(least) - 1)], 1)


def successors(b: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the one after it; the last one is not."""
    step = np.sign(b[1:].astype(np.int16) - b[:-1])
    at = np.where(step != 0, np.arange(len(step)), len(step))
    at = np.minimum.accumulate(at[::-1])[::-1]
    return np.append(np.append(step, -1)[at] > 0, False)


def suffix_array(raw: bytes, depth: int = LENGTH, wanted: np.ndarray | None = None) -> np.ndarray:
    """The suffixes (those ``wanted``, if given, and some more) in order of their first ``depth`` bytes at least."""
    b = np.frombuffer(raw, np.uint8)
    n = len(b)
    if not n:
        return np.empty(0, np.int64)
    small = successors(b)
    keep = np.ones(n, bool) if wanted is None else wanted.copy()
    while (more := np.flatnonzero(keep[:-1] & ~small[:-1] & ~keep[1:])).size:
        keep[more + 1] = True  # a larger suffix is induced from its successor
    direct = np.flatnonzero(small & keep)
    keys = [raw[i : i + depth] for i in direct.tolist()]
    direct = direct[sorted(range(len(keys)), key=keys.__getitem__)]
    ends = np.cumsum(np.bincount(b[direct], minlength=256))
    queue: list[list[np.ndarray]] = [[] for _ in range(256)]
    if keep[n - 1]:
        queue[b[n - 1]].append(np.array([n - 1]))
    out = []

    def induced(part: np.ndarray, c: int) -> np.ndarray:
        """Deals the larger suffixes before these to their buckets; gives those of this bucket back."""
        before = part[part > 0] - 1
        before = before[keep[before] & ~small[before]]
        first = b[before]
        order = np.argsort(first, kind="stable")
        before, first = before[order], first[order]
        for x in np.unique(first[first > c]).tolist():
            lo, hi = np.searchsorted(first, [x, x + 1]) if x < 255 else (np.searchsorted(first, x), len(first))
            queue[x].append(before[lo:hi])
        return before[first == c]

    for c in range(256):
        wave = np.concatenate(queue[c]) if queue[c] else direct[:0]
        while len(wave):
            out.append(wave)
            wave = induced(wave, c)
        part = direct[ends[c - 1] if c else 0 : ends[c]]
        if len(part):
            out.append(part)
            induced(part, c)
    return np.concatenate(out) if out else direct


def common_prefixes(raw: bytes, order: np.ndarray, cap: int = LENGTH) -> np.ndarray:
    """Common prefix of each suffix of ``order`` with the one before, up to ``cap`` bytes; 0 for the first."""
    out, b = np.zeros(len(order), np.int64), np.frombuffer(raw, np.uint8)
    live = np.arange(1, len(order))
    for d in range(cap):
        x, y = order[live] + d, order[live - 1] + d
        live = live[(np.maximum(x, y) < len(b)) & (b[np.minimum(x, len(b) - 1)] == b[np.minimum(y, len(b) - 1)])]
        if not len(live):
            break
        out[live] += 1
    return out


def same_strings(raw: bytes, x: np.ndarray, y: np.ndarray, length: int) -> np.ndarray:
    """Whether the strings of ``length`` bytes at each place of x and of y are equal; pairs one after another at the same distance are compared at once."""
    h = gram_hashes(np.frombuffer(raw, np.uint8), length)
    same = h[x] == h[y]
    like = np.flatnonzero(same)
    gap = y[like] - x[like]
    like = like[np.argsort(gap * len(raw) + x[like])]
    at, gap = x[like], y[like] - x[like]
    cuts = (np.flatnonzero((np.diff(at) != 1) | (np.diff(gap) != 0)) + 1).tolist()
    for a, b in zip([0, *cuts], [*cuts, len(like)], strict=True):
        if a == b:
            continue
        i, j, n = int(at[a]), int(at[a] + gap[a]), b - a
        if raw[i : i + n - 1 + length] != raw[j : j + n - 1 + length]:  # a hash met by chance
            same[like[a:b]] = [raw[i + k : i + k + length] == raw[j + k : j + k + length] for k in range(n)]
    return same


def repeats(parts: list[tuple[bytes, int, int, bool]], length: int = LENGTH) -> list[np.ndarray]:
    """For each part (bytes, starts to judge, place in its text, whether it occurs more than once): which starts repeat."""
    raw = b"".join(x[0] for x in parts)
    sizes = np.array([len(x[0]) for x in parts])
    judged = np.minimum(np.array([x[1] for x in parts]), np.maximum(0, sizes - length + 1))
    of, base = np.repeat(np.arange(len(parts)), sizes), np.cumsum(sizes) - sizes
    inside = np.arange(len(raw)) - base[of]
    wanted = inside < judged[of]
    order = suffix_array(raw, length, wanted)
    order = order[wanted[order]]
    hit = np.zeros(len(raw), bool)
    if len(order):
        new = np.append(True, ~same_strings(raw, order[1:], order[:-1], length))
        heads = np.flatnonzero(new)
        with np.errstate(over="ignore"):
            ident = np.array([x[2] for x in parts], np.int64)[of[order]] + inside[order]
        many = np.array([x[3] for x in parts])[of[order]]
        again = (np.minimum.reduceat(ident, heads) != np.maximum.reduceat(ident, heads)) | np.logical_or.reduceat(many, heads)
        hit[order] = again[np.cumsum(new) - 1]
    return [hit[s : s + j] for s, j in zip(base.tolist(), judged.tolist(), strict=True)]


def spans(hits: list[np.ndarray]) -> list[list[tuple[int, int]]]:
    """First and last place of each run of hits, by part."""
    apart = np.zeros(1, bool)
    flat = np.concatenate([apart, *(x for hit in hits for x in (hit, apart))])
    edge = np.flatnonzero(flat[1:] != flat[:-1])
    base = np.cumsum([0, *(len(x) + 1 for x in hits)])
    of = np.searchsorted(base, edge[::2], "right") - 1
    runs = list(zip((edge[::2] - base[of]).tolist(), (edge[1::2] - 1 - base[of]).tolist(), strict=True))
    bounds = np.searchsorted(of, np.arange(len(hits) + 1)).tolist()
    return [runs[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]


def places(rid: np.ndarray, at: np.ndarray) -> np.ndarray:
    """A number for each place in a text, so that places are told apart and neighbours are numbered on."""
    with np.errstate(over="ignore"):
        return (rid.astype(np.uint64) * np.uint64(_BASE) + at.astype(np.uint64)).view(np.int64)


def signed(x: int) -> int:
    return x - 2**64 if x >= 2**63 else x


def around(text: bytes) -> tuple[np.ndarray, np.ndarray] | None:
    """Hashes of the grams that anchor the strings of PASSAGE words, and SIDE bytes for the blocks to the left and to the right of each; 0 stands for none."""
    h = word_hashes(text)
    if len(h) < PASSAGE:
        return None
    sums = prefix_sums(h)
    grams, blocks = gram_hashes(h, WORDS, sums), (gram_hashes(h, STEP, sums) % np.uint64(255)).astype(np.uint8) + np.uint8(1)
    wide = PASSAGE - WORDS + 1
    pad = np.zeros(wide - 1, np.uint64)
    at = np.flatnonzero(sliding(np.concatenate([pad, sliding(grams, wide), pad]), wide, np.maximum) == grams)
    left, right = at[:, None] - STEP * np.arange(1, SIDE + 1), at[:, None] + WORDS + STEP * np.arange(SIDE)
    both = np.concatenate([left, right], 1)
    inside = (both >= 0) & (both < len(blocks))
    return grams[at], np.where(inside, blocks[np.where(inside, both, 0)], 0).astype(np.uint8)


def worded(parts: int):
    """The anchors of words of a slice of texts, dealt by their hash: one row for each part."""

    def each(batch: pa.RecordBatch) -> dict | None:
        rids, found = batch["rid"].to_pylist(), [around(x) for x in batch["text"].to_pylist()]
        some = [i for i, x in enumerate(found) if x]
        if not some:
            return None
        keys, sides = (np.concatenate([found[i][j] for i in some]) for j in (0, 1))
        # rows of a slice are numbered on, so that a byte tells them apart; 48 bits of a gram's hash do within a part
        at = np.repeat(np.array([rids[i] - rids[0] for i in some], np.uint8), [len(found[i][0]) for i in some])
        part = (keys % np.uint64(parts)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        cuts = np.flatnonzero(np.diff(part[order])) + 1
        runs = [*zip([0, *cuts.tolist()], [*cuts.tolist(), len(order)], strict=True)]
        keys, sides, at = keys[order], sides[order], at[order]
        out = {"part": [int(part[order[a]]) for a, _ in runs], "base": [rids[0]] * len(runs)}
        return out | {"keys": [keys[a:b].view(np.uint8).reshape(-1, 8)[:, 2:].tobytes() for a, b in runs], "sides": [sides[a:b].tobytes() for a, b in runs], "at": [at[a:b].tobytes() for a, b in runs]}

    return each


def met(rows: pa.Table) -> pa.Table:
    """(rid, marks): how many anchors of each text have surroundings that another text has, from all anchors of one part."""
    join = lambda c, t: np.frombuffer(b"".join(rows[c].to_pylist()), t)
    sides = join("sides", np.uint8).reshape(-1, 2 * SIDE)
    keys = np.zeros((len(sides), 8), np.uint8)
    keys[:, 2:] = join("keys", np.uint8).reshape(-1, 6)
    keys = keys.view(np.uint64).reshape(-1)
    rid = np.repeat(rows["base"].to_numpy(), [len(x) for x in rows["at"].to_pylist()]) + join("at", np.uint8)
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    live = np.sort(order[np.append(same, False) | np.insert(same, 0, False)])  # a gram that occurs once meets nothing
    keys, sides, rid = keys[live], sides[live], rid[live]
    hit = np.zeros(len(keys), bool)
    for n in range(COVERED + 1):
        # n blocks to the left and the others to the right
        block = np.concatenate([sides[:, :n], sides[:, SIDE : SIDE + COVERED - n]], 1)
        whole = np.flatnonzero((block > 0).all(1))
        with np.errstate(over="ignore"):
            code = keys[whole].copy()
            for c in range(COVERED):
                code = (code ^ block[whole, c]) * np.uint64(_BASE)
                code ^= code >> np.uint64(29)
        order = np.argsort(code, kind="stable")
        heads = np.flatnonzero(np.append(True, code[order][1:] != code[order][:-1])) if len(order) else order
        if len(heads):
            of = rid[whole][order]
            many = np.minimum.reduceat(of, heads) != np.maximum.reduceat(of, heads)
            hit[whole[order]] |= np.repeat(many, np.diff(np.append(heads, len(order))))
    found, marks = np.unique(rid[hit], return_counts=True)
    return pa.table({"rid": pa.array(found, pa.int64()), "marks": pa.array(marks, pa.int64())})


def shared_passages(rows: DataFrame) -> DataFrame:
    """(rid, marks) of the texts of ``rows(rid, text)`` that share a passage with another one.

    Every passage of more than PASSAGE words (runs of bytes other than white
    space) that occurs in two texts is marked; so may be one that holds an
    anchor and COVERED blocks of STEP words.
    """
    parts = C.width(rows.sparkSession)
    dealt = C.map_rows(rows, lambda: worded(parts), "part int, base long, keys binary, sides binary, at binary")
    return dealt.groupBy("part").applyInArrow(met, "rid long, marks long").groupBy("rid").agg(F.sum("marks").alias("marks"))


def packed(p: Column, left: Column, right: Column) -> Column:
    """A place, and the reach of its context to both sides, in one number; a reach is less than 2**11."""
    return F.shiftleft(p.cast("long"), 22) + F.shiftleft(left.cast("long"), 11) + right


def place_of(pack: Column) -> Column:
    return F.shiftright(pack, 22)


def left_of(pack: Column) -> Column:
    return F.shiftright(pack, 11).bitwiseAND(F.lit(2047))


def right_of(pack: Column) -> Column:
    return pack.bitwiseAND(F.lit(2047))


NONE = bytes(8)


def marked(length: int):
    """(rid, p, h1, h2, left, right, kl, kr) of each anchor: its context's hashes, and the keys of both sides.

    A context holds the strings judged at its anchor and nothing else.
    """
    half = length // 2 - GRAM // 2
    if 2 * length >= 2**11:
        raise ValueError("strings are too long for the packed reach of a context")

    def each(batch: pa.RecordBatch) -> dict | None:
        found, both, left, right = [], [], [], []
        xxh, whole = xxhash.xxh64_digest, xxhash.xxh3_128_digest
        for text in batch["text"].to_pylist():
            at = anchors(text, length)
            found.append(at)
            for p, a, b in at.tolist():
                both.append(whole(text[a : b + length], p - a))
                # a string that reaches at least ``half`` to the left covers the first part, any other the second
                left.append(xxh(text[p - half : p + GRAM], 1) if a <= p - half else NONE)
                right.append(xxh(text[p : p + length - half + 1], 2) if b > p - half else NONE)
        if not both:
            return None
        p, a, b = np.concatenate(found).T
        numbers = lambda x: np.frombuffer(b"".join(x), np.int64)
        rid, h = np.repeat(batch["rid"].to_numpy(), list(map(len, found))), numbers(both).reshape(-1, 2)
        out = {"rid": rid, "p": p, "h1": h[:, 0].copy(), "h2": h[:, 1].copy(), "left": p - a, "right": b + length - p}
        return out | {"kl": pa.array(numbers(left), mask=a > p - half), "kr": pa.array(numbers(right), mask=b <= p - half)}

    return each


def cut_out(length: int):
    """The bytes of each context that strings of its side cover, from texts with the anchors asked for."""
    half = length // 2 - GRAM // 2

    def each(batch: pa.RecordBatch) -> dict | None:
        every = batch["asked"].flatten()
        if not len(every):
            return None
        out = {f.name: x for f, x in zip(every.type, every.flatten(), strict=True)}
        of = np.repeat(np.arange(batch.num_rows), batch["asked"].value_lengths().to_numpy())
        p, left, right, side = (out.pop(c).to_numpy().astype(np.int64) for c in ("p", "left", "right", "side"))
        a, b = p - left, p + right - length
        low, last = np.where(side == 0, a, np.maximum(a, p - half + 1)), np.where(side == 0, np.minimum(b, p - half), b)
        texts = batch["text"].to_pylist()
        raw = [texts[i][x:y] for i, x, y in zip(of.tolist(), low.tolist(), (last + length).tolist(), strict=True)]
        return out | {"at": places(batch["rid"].to_numpy()[of], low), "back": p - low, "judged": last - low + 1, "bytes": raw, "side": side}

    return each


FOUND = "h1 long, h2 long, first long, last long, w1 long, w2 long, at long, sure boolean"


def shared_start(x: bytes, y: bytes) -> int:
    """Length of the common beginning."""
    low, high = 0, min(len(x), len(y))
    if x[:high] == y[:high]:
        return high
    while high - low > 1:
        mid = (low + high) // 2
        if x[:mid] == y[:mid]:
            low = mid
        else:
            high = mid
    return low


def reach(parts: list[bytes]) -> list[int]:
    """The longest beginning that each part shares with another: one of its neighbours in order has it."""
    order, out = sorted(range(len(parts)), key=parts.__getitem__), [0] * len(parts)
    for i, j in zip(order, order[1:], strict=False):
        n = shared_start(parts[i], parts[j])
        out[i], out[j] = max(out[i], n), max(out[j], n)
    return out


def trimmed(rows: list[tuple], length: int) -> dict[bytes, list[tuple]]:
    """Contexts of one key cut to what others share, by their bytes: (row, start of the cut); too short ones are dropped."""
    half = length // 2 - GRAM // 2
    left = rows[0][8]  # the side
    cores = [(back - half, back + GRAM) if left == 0 else (back, back + length - half + 1) for back in (r[6] for r in rows)]
    before = reach([r[7][:a][::-1] for r, (a, _) in zip(rows, cores, strict=True)])
    after = reach([r[7][b:] for r, (_, b) in zip(rows, cores, strict=True)])
    out: dict[bytes, list[tuple]] = {}
    for r, (a, b), x, y in zip(rows, cores, before, after, strict=True):
        if b + y - (a - x) >= length:
            out.setdefault(r[7][a - x : b + y], []).append((r, a - x))
    return out


def counted(parts: list[tuple[bytes, int, int, bool]], length: int, slices: int = 16) -> list[np.ndarray]:
    """As ``repeats``, by counting the strings of one slice of hashes after the other."""
    hits = [np.zeros(x[1], bool) for x in parts]
    for turn in range(slices):
        seen: dict[bytes, tuple[int, list]] = {}
        for i, (raw, judged, ident, many) in enumerate(parts):
            for j in range(judged):
                h = xxhash.xxh3_128_digest(raw[j : j + length])
                if h[0] % slices == turn:
                    first, at = seen.setdefault(h, (ident + j, []))
                    if many or first != ident + j:
                        at.append(None)
                    at.append((i, j))
        for _, at in seen.values():
            if None in at:
                for x in at:
                    if x:
                        hits[x[0]][x[1]] = True
    return hits


FIELDS = ("key", "h1", "h2", "many", "at", "judged", "back", "bytes", "side")


def sorted_out(length: int):
    """Repeated starts by context, from the anchor, of whole groups in batches; of hot groups the strings to count."""
    group: list[tuple] = []
    held: list[tuple[bytes, list[tuple]]] = []
    state = {"bytes": 0, "key": None}
    names = ("h1", "h2", "first", "last", "w1", "w2", "at", "sure")

    def close_group() -> None:
        found = trimmed(group, length) if len(group) > 1 else {}
        group.clear()
        held.extend(found.items())
        state["bytes"] += sum(map(len, found))

    def settle() -> list[tuple]:
        out = []
        if held:
            # contexts of one text may overlap and be cut to the very same place, which is no repeat
            idents = [{signed((r[4] + cut) % 2**64) for r, cut in of} for _, of in held]
            parts = [(raw, len(raw) - length + 1, min(x), len(x) > 1 or any(r[3] for r, _ in of)) for (raw, of), x in zip(held, idents, strict=True)]
            for (_, of), runs in zip(held, spans((repeats if state["bytes"] <= MOST else counted)(parts, length)), strict=True):
                out += [(r[1], r[2], a + cut - r[6], b + cut - r[6], None, None, None, None) for r, cut in of for a, b in runs]
        held.clear()
        state["bytes"] = 0
        return out

    def each(batch: pa.RecordBatch | None) -> dict | None:
        out = []
        if batch is None:
            close_group()
            out += settle()
        else:
            hot = batch["hot"].to_pylist()
            for row, loose in zip(zip(*(batch[c].to_pylist() for c in FIELDS), strict=True), hot, strict=True):
                if loose:
                    _, h1, h2, many, at, judged, back, raw, _ = row
                    for i in range(min(judged, len(raw) - length + 1)):
                        w1, w2 = (signed(xxhash.xxh64_intdigest(raw[i : i + length], seed)) for seed in (3, 4))
                        out.append((h1, h2, i - back, i - back, w1, w2, signed((at + i) % 2**64), many))
                    continue
                if row[0] != state["key"]:
                    close_group()
                    state["key"] = row[0]
                    if state["bytes"] > BATCH:
                        out += settle()
                group.append(row)
        return {k: [x[i] for x in out] for i, k in enumerate(names)} if out else None

    return each


def removed(length: int):
    def each(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {x: [] for x in ("doc_id", "n_bytes", "n_removed", "n_spans", "kept", "spans", "n_shared")}
        for doc_id, text, starts, marks in zip(*(batch[c].to_pylist() for c in ("doc_id", "text", "starts", "marks")), strict=True):
            runs: list[list[int]] = []
            for a, b in sorted((x["a"], x["b"] + length) for x in starts or ()):
                if runs and a <= runs[-1][1]:
                    runs[-1][1] = max(runs[-1][1], b)
                else:
                    runs.append([a, b])
            cuts = [0, *(x for r in runs for x in r), len(text)]
            row = (doc_id, len(text), sum(b - a for a, b in runs), len(runs), b"".join(text[a:b] for a, b in zip(cuts[::2], cuts[1::2], strict=True)), [x for r in runs for x in r], marks or 0)
            for k, v in zip(out, row, strict=True):
                out[k].append(v)
        return out

    return each


def repeated_starts(rows: DataFrame, length: int = LENGTH) -> DataFrame:
    """(rid, a, b): runs of places in the texts of ``rows(rid, text)`` where a string of ``length`` bytes starts that starts elsewhere too."""
    spark = rows.sparkSession
    every = C.map_rows(rows, lambda: marked(length), "rid long, p int, h1 long, h2 long, left int, right int, kl long, kr long")
    every = C.cut(every.select("rid", packed(F.col("p"), F.col("left"), F.col("right")).alias("pack"), "h1", "h2", "kl", "kr"), "anchors")
    context = ["h1", "h2"]
    # all of a context's anchors have the same bytes around them, so any of them stands for it
    one = every.groupBy(*context).agg(F.count("*").alias("n"), *[F.first(c).alias(c) for c in ("rid", "pack", "kl", "kr")])
    one = C.cut(one, "contexts", clear=True)
    side = F.posexplode(F.array("kl", "kr")).alias("side", "key")
    sides = one.select(*context, "rid", ((F.col("pack") * 2) + (F.col("n") > 1).cast("long")).alias("pack"), side).where("key is not null")
    sides = sides.select("key", *context, "rid", (F.col("pack") * 2 + F.col("side")).alias("pack"))
    many = (F.shiftright("pack", 1).bitwiseAND(F.lit(1)) == 1).alias("many")
    shared = sides.groupBy("key").agg(F.count("*").alias("k"), F.min(many).alias("settled")).where("k > 1 and not settled")
    place = F.shiftright("pack", 2)
    what = ["key", (F.col("k") > GROUP).alias("hot"), F.when(F.col("k") > GROUP, F.pmod(F.xxhash64("h1"), F.ceil(F.col("k") / 1024))).otherwise(0).cast("int").alias("salt"), *context, many, F.col("pack").bitwiseAND(F.lit(1)).cast("int").alias("side")]
    asked = sides.join(shared, "key").select("rid", *what, left_of(place).cast("int").alias("left"), right_of(place).cast("int").alias("right"), place_of(place).cast("int").alias("p"))
    by_text = asked.groupBy("rid").agg(F.collect_list(F.struct("key", "salt", "hot", *context, "many", "side", "left", "right", "p")).alias("asked"))
    bits = C.map_rows(rows.join(by_text, "rid"), lambda: cut_out(length), "key long, salt int, hot boolean, h1 long, h2 long, many boolean, at long, back int, judged int, bytes binary, side int")
    groups = bits.repartition(C.width(spark), "key", "salt").sortWithinPartitions("hot", "key")
    found = C.cut(C.map_rows(groups, lambda: sorted_out(length), FOUND, flush=True), "found", clear=True)
    open_ = found.where("w1 is not null")
    again = open_.groupBy("w1", "w2").agg(F.min("at").alias("x"), F.max("at").alias("y"), F.max("sure").alias("sure")).where("x <> y or sure").select("w1", "w2")
    starts = found.where("w1 is null").select(*context, "first", "last").union(open_.where("not sure").join(again, ["w1", "w2"]).select(*context, "first", "last"))
    # runs of places by context, with all of its places for one that occurs more than once
    copies = one.where((F.col("n") > 1) & (left_of(F.col("pack")) + right_of(F.col("pack")) >= length))
    whole = copies.select(*context, (-left_of(F.col("pack"))).alias("first"), F.least(F.lit(0), right_of(F.col("pack")) - length).alias("last"), F.col("n").alias("times"))
    runs = starts.select(*context, "first", "last", F.lit(1).cast("long").alias("times")).join(whole.select(*context), context, "left_anti").unionByName(whole)
    found_at = C.join_on_key(every.select("rid", "pack", *context), runs, context, "times", every.count())
    return found_at.select("rid", (place_of(F.col("pack")) + F.col("first")).alias("a"), (place_of(F.col("pack")) + F.col("last")).alias("b"))


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept, spans, n_shared) of every row; ``spans`` holds the bounds removed.

    ``n_shared`` is over zero where the text shares a passage of more than PASSAGE
    words with another one, however few its bytes.  Null texts count as empty;
    texts shorter than ``length`` stay whole; rows that
    repeat a doc_id are texts of their own, so equal ones remove each other; an
    empty table gives no rows.  Strings are judged on the input.
    """
    rows = C.stable(docs).select(F.monotonically_increasing_id().alias("rid"), "doc_id", C.text_bytes().alias("text"))
    texts = rows.select("rid", "text")
    marks = C.cut(shared_passages(texts), "marks", clear=True).select("rid", F.lit(None).cast("struct<a:long,b:long>").alias("run"), "marks")
    runs = repeated_starts(texts, length).select("rid", F.struct(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).alias("run"), F.lit(0).cast("long").alias("marks"))
    told = runs.union(marks).groupBy("rid").agg(F.collect_list("run").alias("starts"), F.sum("marks").alias("marks"))
    return C.map_rows(rows.join(told, "rid", "left"), lambda: removed(length), "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, spans array<long>, n_shared long")


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = remove_repeats(C.documents(spark, sf_dir))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), "n_shared")


QUERIES = {"op6_suffix_dedup": op6_suffix_dedup}
ORACLES: dict[str, str] = {}
