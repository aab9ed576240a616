"""LM scoring with a causal self-attention model trained in numpy.

Texts are lower-cased words followed by one end, spelled in the subword ids of a
public model.  The chance of the next id is that of its class, from masked
attention over a window of ids, times that of the id in its class after the
id before, from counts over every training text.  Windows overlap: each
scores its last STRIDE ids once, with the ids before as context.  The attention is
trained where the texts lie, on every word of every training text: each task takes
its own gradient steps, and their changes are averaged.  The chance of a word is that of its class (its first
id's, from the attention) times its discounted share among the training words of
the class; what the discount takes goes to words by their ids.  The discount is told by how
many of all words occur once and twice.  Beside it stands a smoothed word unigram, whose
counts are exact over all training words: frequent words are looked up in a table
of bounded size, the rest are joined.
"""

from __future__ import annotations

import hashlib
import os
from collections import Counter
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

MODEL = os.environ.get("PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")
WINDOW, STRIDE, WIDTH, CLASSES, SINGLE = 24, 20, 8, 64, 48
LEFT = WINDOW - STRIDE
#: Ids with a row of their own in the tables of the attention model.
ROWS = 768
#: Ids that are counted apart after each row; the others of a class are counted together and told apart by their own counts.
COLUMNS = 2048
#: Which ids keep company in a text is told for so many ids, by so many of them.
TOLD, BY = 2048, 48
#: How many places before each place that is scored each place of its window lies.
GAPS = np.arange(LEFT, WINDOW)[:, None] - np.arange(WINDOW)[None, :]
#: Products up to this size are raised to powers without their largest taken off.
REACH = 40
#: Windows worked on at once, in scoring and in a gradient step.
BLOCK, STEP = 256, 128
#: Discounts that are taken.
DISCOUNTS = tuple(x / 20 for x in range(1, 20))
#: Ids that a task trains on before it takes the next texts.
TURN = 1 << 20
#: Words counted in a task before their counts are passed on.
KEPT = 600_000
#: Words looked up without a join, and the longest of them in bytes; longer ones are known by a digest.
HOT, LONG = 300_000, 64
START, END = 1, 2
END_WORD = b""


_CODERS: dict = {}


def coder(model: str):
    """The public model's coder, read once in a process."""
    if model not in _CODERS:
        import sentencepiece

        _CODERS[model] = sentencepiece.SentencePieceProcessor(model_file=model)
    return _CODERS[model]


class Spelled:
    """The ids of distinct words, one after another."""

    def __init__(self, words: list[bytes], model: str):
        ids = coder(model).encode([w.decode("utf-8", "replace") for w in words]) if words else []
        self.lengths = np.fromiter(map(len, ids), np.int64, len(ids))
        self.flat = np.fromiter(chain.from_iterable(ids), np.int32, int(self.lengths.sum()))
        self.first = np.cumsum(self.lengths) - self.lengths


class Slice:
    """The words of some texts, each text with its end: distinct words, and every text as a run of ids.

    Words in ``known`` have their place in ``table``; the others are spelled here.
    """

    def __init__(self, texts: list[bytes], model: str, known: dict[bytes, int], table: Spelled):
        seen: dict[bytes, int] = {END_WORD: 0}
        parts = [C.words(x) for x in texts]
        put = seen.setdefault
        self.index = np.fromiter((put(w, len(seen)) for p in parts for w in (*p, END_WORD)), np.int64, sum(map(len, parts)) + len(parts))
        self.words = list(seen)
        get = known.get
        self.place = np.fromiter((get(w, -1) for w in self.words), np.int64, len(self.words))
        new = np.flatnonzero(self.place < 0)
        new = new[new > 0]
        rare = Spelled([self.words[i] for i in new.tolist()], model)
        flat = np.concatenate([table.flat, rare.flat, np.array([END], np.int32)])
        lengths, first = np.empty(len(seen), np.int64), np.empty(len(seen), np.int64)
        old = np.flatnonzero(self.place >= 0)
        lengths[old], first[old] = table.lengths[self.place[old]], table.first[self.place[old]]
        lengths[new], first[new] = rare.lengths, len(table.flat) + rare.first
        lengths[0], first[0] = 1, len(flat) - 1
        self.sizes = lengths[self.index]
        self.at = np.cumsum(self.sizes) - self.sizes
        self.ids = flat[np.repeat(first[self.index] - self.at, self.sizes) + np.arange(int(self.sizes.sum()))]
        self.ends = np.flatnonzero(self.index == 0) + 1  # of each text, in words
        stops = np.append(self.at, len(self.ids))[self.ends]
        self.texts = [np.concatenate([[START], x]).astype(np.int32) for x in np.split(self.ids, stops[:-1])]


def added_by(table: np.ndarray, rows: np.ndarray, values: np.ndarray) -> None:
    """Adds each of ``values`` to its row, by runs of equal rows."""
    rows = rows.astype(np.int16)  # short numbers are sorted by digits
    order = np.argsort(rows, kind="stable")
    rows = rows[order]
    heads = np.flatnonzero(np.append(True, rows[1:] != rows[:-1])) if len(order) else order
    if len(heads):
        table[rows[heads]] += np.add.reduceat(values[order], heads)


@dataclass
class Net:
    """Attention tables (query, key, value by row; bias by distance), class outputs, and the class of each id."""

    params: dict[str, np.ndarray]
    row: np.ndarray
    cls: np.ndarray
    column: np.ndarray

    def windows(self, texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, next ids, text) of all windows; places outside a text hold -1."""
        counts = [-(-(len(x) - 1) // STRIDE) for x in texts]
        total, at = sum(counts), 0
        ids = np.full((total, WINDOW), -1, np.int32)
        then = np.full((total, STRIDE), -1, np.int32)
        for x, n in zip(texts, counts, strict=True):
            flat = np.full(LEFT + n * STRIDE, -1, np.int32)
            flat[LEFT : LEFT + len(x) - 1] = x[:-1]
            ids[at : at + n] = np.lib.stride_tricks.sliding_window_view(flat, WINDOW)[::STRIDE]
            flat = np.full(n * STRIDE, -1, np.int32)
            flat[: len(x) - 1] = x[1:]
            then[at : at + n] = flat.reshape(n, STRIDE)
            at += n
        return ids, then, np.repeat(np.arange(len(texts)), counts)

    def forward(self, ids: np.ndarray) -> tuple:
        p, r = self.params, self.row[ids]
        here, both = r[:, LEFT:], np.concatenate([p["k"], p["v"], np.ones_like(p["v"][:, :1])], 1).take(r, 0)
        q, k, v = p["q"].take(here, 0), both[..., :WIDTH], both[..., WIDTH:]
        s = q @ k.transpose(0, 2, 1)
        s += self.bias()
        if not self.small("q", "k"):
            s += np.where(ids < 0, np.float32(-1e9), np.float32(0))[:, None, :]
            s -= s.max(2, keepdims=True)
        np.exp(s, out=s)
        outside = np.flatnonzero((ids < 0).any(1))
        s[outside] *= (ids[outside] >= 0)[:, None, :]
        a = s @ v
        total = a[..., WIDTH:]
        a, v = a[..., :WIDTH] / total, v[..., :WIDTH]
        logits = a.reshape(-1, WIDTH) @ p["out"]
        logits += p["next"].take(here.reshape(-1), 0)
        if not self.small("v", "out"):
            logits -= logits.max(1, keepdims=True)
        return here, r, q, k, v, s, total, a, logits

    def small(self, x: str, y: str) -> bool:
        """Whether the powers of all products of a row of ``x`` with one of ``y`` are within a float's reach as they are."""
        far = [np.sqrt((self.params[n] ** 2).sum(0 if n == "out" else 1)).max() for n in (x, y)]
        return float(far[0]) * float(far[1]) + float(np.abs(self.params["gap"]).max()) < REACH

    def bias(self) -> np.ndarray:
        return np.where(GAPS >= 0, self.params["gap"][np.maximum(GAPS, 0)], np.float32(-1e9)).astype(np.float32)

    def log_class(self, ids: np.ndarray, then: np.ndarray) -> np.ndarray:
        """log chance of the class of each next id."""
        return self.log_classes(ids, then)[0]

    def log_classes(self, ids: np.ndarray, then: np.ndarray, begins: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None]:
        """log chance of the class of each next id, and that it is one of the classes ``begins``."""
        logits = self.forward(ids)[-1]
        picked = logits[np.arange(len(logits)), self.cls[then].reshape(-1)]
        np.exp(logits, out=logits)
        sums = np.log(logits @ np.stack([np.ones(CLASSES), np.ones(CLASSES) if begins is None else begins], 1).astype(np.float32))
        return (picked - sums[:, 0]).reshape(then.shape), None if begins is None else (sums[:, 1] - sums[:, 0]).reshape(then.shape)

    def gradient(self, ids: np.ndarray, then: np.ndarray, counted: bool = False) -> dict[str, np.ndarray]:
        """Of all weights, or of those that aren't known from counts."""
        p = self.params
        here, r, q, k, v, s, total, a, e = self.forward(ids)
        live, goal = (then >= 0).reshape(-1), self.cls[then].reshape(-1)
        share = (live / max(1, live.sum())).astype(np.float32)
        np.exp(e, out=e)
        e *= (share / (e @ np.ones(CLASSES, np.float32)))[:, None]
        e[np.arange(len(e)), goal] -= share
        g = {n: np.zeros_like(x) for n, x in p.items() if n not in "qkv" and not (counted and n == "next")}
        if not counted:
            added_by(g["next"], here.reshape(-1), e)
        g["out"] = a.reshape(-1, WIDTH).T @ e
        da = (e @ p["out"].T).reshape(a.shape)
        s /= total
        by = np.zeros((*ids.shape, 3 * WIDTH), np.float32)
        np.matmul(s.transpose(0, 2, 1), da, out=by[..., 2 * WIDTH :])
        ds = da @ v.transpose(0, 2, 1)
        ds -= np.einsum("ijk,ijk->ij", da, a)[..., None]  # the mean of what it is taken from
        ds *= s
        np.matmul(ds, k, out=by[:, LEFT:, :WIDTH])
        np.matmul(ds.transpose(0, 2, 1), q, out=by[..., WIDTH : 2 * WIDTH])
        sums = np.zeros((ROWS + 4, 3 * WIDTH), np.float32)
        added_by(sums, r.reshape(-1), by.reshape(-1, 3 * WIDTH))
        g |= {n: sums[:, i * WIDTH : (i + 1) * WIDTH] for i, n in enumerate("qkv")}
        g["gap"] = np.bincount(GAPS[GAPS >= 0], ds.sum(0)[GAPS >= 0], WINDOW).astype(np.float32)
        return g


def alike(company: np.ndarray, n: int, rounds: int = 12) -> np.ndarray:
    """``n`` groups of rows with like shares, by weighted means from rows far apart."""
    mass = company.sum(1)
    x = np.sqrt(company / np.maximum(mass, 1)[:, None])
    means = x[[int(mass.argmax())]] if len(x) else x
    for _ in range(n - 1):
        gap = ((x[:, None] - means[None]) ** 2).sum(2).min(1)
        means = np.append(means, x[[int((gap * mass).argmax())]], 0)
    for _ in range(rounds):
        to = (2 * x @ means.T - (means**2).sum(1)).argmax(1)
        for j in range(n):
            if mass[to == j].sum() > 0:
                means[j] = np.average(x[to == j], 0, mass[to == j])
    return to


def laid_out(seen: np.ndarray, initial: np.ndarray, company: np.ndarray | None = None) -> Net:
    """Classes, rows and columns by the counts of all ids; ``initial`` marks ids that begin words.  The weights are those before training.

    Ids that begin words and have no class of their own are grouped by ``company``, how often the TOLD most frequent
    ids share a text with the BY most frequent ones; those without any, and all others, by how frequent they are.
    """
    size = len(seen)
    order = np.lexsort((np.arange(size), -seen))
    cls = np.zeros(size, np.int32)
    single = [i for i in order if i not in (START, END)][: SINGLE - 1]
    cls[END], at = 0, 1
    for i in single:
        cls[i] = at
        at += 1
    rest = np.setdiff1d(order, [END, *single], assume_unique=True)
    groups = CLASSES - at
    for part, n in ((rest[initial[rest]], groups // 2), (rest[~initial[rest]], groups - groups // 2)):
        part = part[np.lexsort((part, -seen[part]))]
        mass = np.cumsum(seen[part] + 0.01)
        cls[part] = at + np.minimum(n - 1, (mass / (mass[-1] if len(mass) else 1) * n).astype(int)) if len(part) else 0
        if company is not None and len(part) and initial[part[0]]:
            told = order[: len(company)]
            of = np.flatnonzero(np.isin(told, part) & (company.sum(1) > 0))
            if len(of) > n:
                cls[told[of]] = at + alike(company[of].astype(float), n)
        at += n
    row = np.full(size + 1, ROWS, np.int32)
    row[:size][initial] = ROWS + 1
    row[order[:ROWS]] = np.arange(min(size, ROWS))
    row[START], row[size] = ROWS + 2, ROWS + 3  # the last is for places outside a text
    column = np.full(size + 1, COLUMNS, np.int32)
    column[order[:COLUMNS]] = np.arange(min(size, COLUMNS))
    draw = np.random.default_rng(5)
    n = ROWS + 4
    params = {name: draw.normal(0, 0.3, (n, WIDTH)).astype(np.float32) for name in "qkv"}
    params |= {"gap": np.zeros(WINDOW, np.float32), "out": draw.normal(0, 0.1, (WIDTH, CLASSES)).astype(np.float32), "next": np.zeros((n, CLASSES), np.float32)}
    return Net(params, row, np.append(cls, 0).astype(np.int32), column)


def after_rows(net: Net, texts: list[np.ndarray]) -> np.ndarray:
    """Counts of classes after rows."""
    at = [net.row[x[:-1]].astype(np.int64) * CLASSES + net.cls[x[1:]] for x in texts]
    return np.bincount(np.concatenate(at), minlength=(ROWS + 4) * CLASSES).reshape(-1, CLASSES) if at else np.zeros((ROWS + 4, CLASSES), np.int64)


def log_after(pairs: np.ndarray) -> np.ndarray:
    """Smoothed log chances of classes after rows."""
    prior = (pairs.sum(0) + 1) / (pairs.sum() + CLASSES)
    return np.log((pairs + 20 * prior) / (pairs.sum(1, keepdims=True) + 20)).astype(np.float32)


class Training:
    """Turns of Adam over the windows of some texts after others, for the attention on top of the counts of classes after rows."""

    def __init__(self, net: Net, rate: float = 0.02):
        self.net = Net({k: x.copy() for k, x in net.params.items()}, net.row, net.cls, net.column)
        self.params = {k: x for k, x in self.net.params.items() if k != "next"}
        self.m, self.v = ({k: 0 * x for k, x in self.params.items()} for _ in range(2))
        self.pairs, self.weight, self.t, self.rate = np.zeros((ROWS + 4, CLASSES), np.int64), 0, 0, rate

    def turn(self, texts: list[np.ndarray]) -> None:
        """Once over all windows of ``texts``; the counts are those of all texts so far."""
        self.pairs += after_rows(self.net, texts)
        self.weight += sum(map(len, texts))
        self.net.params["next"] = log_after(self.pairs)
        ids, then, _ = self.net.windows(texts)
        turn = np.random.default_rng(len(ids)).permutation(len(ids))
        for at in range(0, len(ids), STEP):
            g = self.net.gradient(ids[turn[at : at + STEP]], then[turn[at : at + STEP]], counted=True)
            self.t += 1
            for k, x in self.params.items():
                self.m[k] = 0.9 * self.m[k] + 0.1 * g[k]
                self.v[k] = 0.999 * self.v[k] + 0.001 * g[k] ** 2
                x -= (self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)).astype(np.float32)


def trained(net: Net, texts: list[np.ndarray]) -> Net:
    """The net after one turn over some texts."""
    training = Training(net)
    training.turn(texts)
    return training.net


def summed(sums: DataFrame, kind: type = float) -> np.ndarray | None:
    """The sum of the vectors ``sums`` that tasks give, each as the bytes of its numbers; None where there is none."""

    def added(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        return pa.table({"sums": pa.array([sum(np.frombuffer(x, kind) for x in rows["sums"].to_pylist()).tobytes()], pa.binary())})

    for groups in (4096, 64):  # a group adds a small part of the tasks' vectors, the driver at most 64
        sums = sums.groupBy(F.pmod(F.xxhash64("sums"), F.lit(groups)).alias("g")).applyInArrow(added, "sums binary")
    found = [np.frombuffer(bytes(r["sums"]), kind) for r in sums.collect()]
    return sum(found) if found else None


def company_of(train: DataFrame, seen: np.ndarray, model: str, known: dict[bytes, int], table: Spelled) -> np.ndarray | None:
    """How often each of the TOLD most frequent ids shares a text with each of the BY most frequent ones, as shares of these in the text."""
    order = np.lexsort((np.arange(len(seen)), -seen))[:TOLD]
    rank = np.full(len(seen), -1)
    rank[order] = np.arange(len(order))
    held = train.sparkSession.sparkContext.broadcast((rank, known, table))

    def make():
        (rank, known, table), sums = held.value, np.zeros((len(order), BY), np.float32)

        def each(batch: pa.RecordBatch | None) -> dict | None:
            if batch is None:
                return {"sums": [sums.tobytes()]}
            texts = Slice(batch["text"].to_pylist(), model, known, table).texts
            of = np.repeat(np.arange(len(texts)), [len(x) - 2 for x in texts])
            told = rank[np.concatenate([x[1:-1] for x in texts])] if texts else of
            of, told = of[told >= 0], told[told >= 0]
            near = told < BY
            by = np.bincount(of[near] * BY + told[near], minlength=len(texts) * BY).reshape(-1, BY)
            share = (by / np.maximum(1, by.sum(1, keepdims=True))).astype(np.float32)
            at = np.bincount(of * len(order) + told, minlength=len(texts) * len(order)).reshape(len(texts), len(order))
            np.add(sums, at.T.astype(np.float32) @ share, out=sums)
            return None

        return each

    total = summed(C.map_rows(train.select("text"), make, "sums binary", flush=True), np.float32)
    return None if total is None else total.reshape(-1, BY)


def learnt(train: DataFrame, net: Net, model: str, known: dict[bytes, int], table: Spelled) -> Net:
    """The net trained by all tasks on all words: counts are summed, changes of weights averaged by the ids they come from."""
    spark = train.sparkSession
    names = [k for k in net.params if k != "next"]
    held = spark.sparkContext.broadcast((net, known, table))

    def make():
        (net, known, table), texts = held.value, []
        training, waiting = Training(net), 0

        def each(batch: pa.RecordBatch | None) -> dict | None:
            nonlocal waiting
            if batch is not None:
                texts.extend(Slice(batch["text"].to_pylist(), model, known, table).texts)
                waiting += sum(map(len, texts[-batch.num_rows :])) if batch.num_rows else 0
            if texts and (batch is None or waiting >= TURN):
                training.turn(texts)
                texts.clear()
                waiting = 0
            if batch is not None or not training.weight:
                return None
            change = [(training.net.params[k] - net.params[k]).astype(float).ravel() * training.weight for k in names]
            return {"sums": [np.concatenate([[float(training.weight)], training.pairs.ravel().astype(float), *change]).tobytes()]}

        return each

    total, at = summed(C.map_rows(train.select("text"), make, "sums binary", flush=True)), 1 + (ROWS + 4) * CLASSES
    if total is None:
        return Net(net.params | {"next": log_after(np.zeros((ROWS + 4, CLASSES)))}, net.row, net.cls, net.column)
    params = dict(net.params) | {"next": log_after(total[1:at].reshape(-1, CLASSES))}
    for k in names:
        size = params[k].size
        params[k] = (params[k] + (total[at : at + size] / total[0]).reshape(params[k].shape)).astype(np.float32)
        at += size
    return Net(params, net.row, net.cls, net.column)


def within(net: Net, pairs: pa.Table, seen: np.ndarray, weight: float = 4.0) -> tuple[np.ndarray, np.ndarray]:
    """log10 chance in its class after each row of each column and of the other ids of a class, and of each id among these; from counts over all training texts."""
    size = len(seen)
    table = np.zeros((ROWS + 4, COLUMNS + CLASSES), np.float32)
    np.add.at(table, tuple(pairs[c].to_numpy() for c in ("row", "column")), pairs["n"].to_numpy().astype(np.float32))
    column, own = net.column[:size], net.cls[:size]
    other = column == COLUMNS
    cls = np.zeros(COLUMNS + CLASSES, np.int64)
    cls[column[~other]] = own[~other]
    cls[COLUMNS:] = np.arange(CLASSES)
    one = np.zeros(COLUMNS + CLASSES)
    one[column[~other]] = seen[~other] + 0.5
    one[COLUMNS:] = np.bincount(own[other], seen[other] + 0.5, CLASSES)
    one /= np.maximum(np.bincount(cls, one, CLASSES), 1e-9)[cls]
    out = np.zeros(table.shape, np.float32)
    with np.errstate(divide="ignore"):
        for r in range(ROWS + 4):
            total = np.bincount(cls, table[r], CLASSES)
            out[r] = np.log10((table[r] + weight * one) / (total + weight)[cls])
    rest = np.bincount(own[other], seen[other] + 0.5, CLASSES)
    return out, np.where(other, np.log10((seen + 0.5) / np.maximum(rest, 0.5)[own]), 0.0)


def fold(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 7 == 2


def spelled_logs(net: Net, inside: tuple[np.ndarray, np.ndarray], begins: np.ndarray, part: Slice) -> tuple[np.ndarray, np.ndarray]:
    """log10 chance of each word's class, as a word begins, and of its ids and their end given the class.

    Where a word begins only the classes ``begins`` can follow; that one of them
    follows is the end of the word before.
    """
    ids, then, _ = net.windows(part.texts)
    after = np.concatenate([[START], part.ids[:-1]])
    after[part.at] = START
    logs, stops = [], []
    for b in range(0, len(ids), BLOCK):
        live = then[b : b + BLOCK] >= 0
        for out, x in zip((logs, stops), net.log_classes(ids[b : b + BLOCK], then[b : b + BLOCK], begins), strict=True):
            out.append(x[live])
    logs, stops = np.concatenate(logs) / np.log(10), np.concatenate(stops)[part.at] / np.log(10)
    place = np.where(net.column < COLUMNS, net.column, COLUMNS + net.cls)
    heads = logs[part.at] - np.where(begins[net.cls[part.ids[part.at]]], stops, 0)
    logs[part.at] = 0
    ended = np.append(stops[1:], 0.0)
    ended[part.ends - 1] = 0  # nothing follows the end of a text
    return heads, np.add.reduceat(logs + inside[0][net.row[after], place[part.ids]] + inside[1][part.ids], part.at) + ended


def log_sum(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """log10 of the sum of two numbers given by their log10."""
    return np.logaddexp(a * np.log(10), b * np.log(10)) / np.log(10)


def key_of(word: bytes) -> bytes:
    """A word, or a digest of one that is long, so that keys are of bounded size."""
    return word if len(word) <= LONG else b"\0" + hashlib.sha256(word).digest()


def key_column() -> Column:
    return F.when(F.length("word") <= LONG, F.col("word")).otherwise(F.concat(F.lit(b"\0"), F.unhex(F.sha2("word", 256))))


def word_counts(train: DataFrame) -> DataFrame:
    """(word, n) over all training texts, with the end; folded in each task before they are shuffled."""

    def make():
        words = Counter()

        def flush() -> dict:
            out = {"word": list(words), "n": list(words.values())}
            words.clear()
            return out

        def each(batch: pa.RecordBatch | None) -> dict | None:
            if batch is None:
                return flush()
            for text in batch["text"].to_pylist():
                words.update(C.words(text))
            words[END_WORD] += batch.num_rows
            return flush() if len(words) > KEPT else None

        return each

    return C.map_rows(train.select("text"), make, "word binary, n long", flush=True).groupBy("word").agg(F.sum("n").alias("n"))


def pair_counts(words: DataFrame, model: str, row: np.ndarray, column: np.ndarray) -> DataFrame:
    """(row, column, n): ids after ids inside the counted words; the first of a word stands after the start.

    With row -1, how often each id occurs, with row -2, how many distinct words begin with it, with row -3, how many words.
    """
    wide = COLUMNS + CLASSES

    def make():
        pairs, by = np.zeros((ROWS + 4) * wide, np.int64), np.zeros((3, len(column)), np.int64)
        seen, kinds, heads = by

        def each(batch: pa.RecordBatch | None) -> dict | None:
            if batch is None:
                at, (which, of) = np.flatnonzero(pairs), np.nonzero(by)
                return {"row": np.append(at // wide, -1 - which), "column": np.append(at % wide, of), "n": np.append(pairs[at], by[which, of])}
            words, n = batch["word"].to_pylist(), batch["n"].to_numpy()
            x = Spelled([w for w in words if w], model)
            n = n[[i for i, w in enumerate(words) if w]]
            times = np.repeat(n, x.lengths)
            before = np.concatenate([[START], x.flat[:-1]]) if len(x.flat) else x.flat
            before[x.first[x.lengths > 0]] = START
            np.add.at(pairs, row[before] * wide + column[x.flat], times)
            np.add.at(seen, x.flat, times)
            begin = x.flat[x.first[x.lengths > 0]]
            np.add.at(kinds, begin, 1)
            np.add.at(heads, begin, n[x.lengths > 0])
            for i, w in enumerate(words):
                if not w:
                    pairs[row[START] * wide + column[END]] += batch["n"][i].as_py()
                    seen[END] += batch["n"][i].as_py()
                    heads[END] += batch["n"][i].as_py()
                    kinds[END] += 1
            return None

        return each

    return C.map_rows(words, make, "row int, column int, n long", flush=True).groupBy("row", "column").agg(F.sum("n").alias("n"))


def score_all(docs: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row.

    Null counts as empty, which is one end; rows that repeat a doc_id get a row
    each; an empty table gives no rows; long texts are read whole, window by
    window.  Texts whose crc32(doc_id) mod 7 is 2 are held out of all learning.
    """
    spark = docs.sparkSession
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", F.coalesce(fold(), F.lit(False)).alias("held_out"), C.text_bytes().alias("text"))
    train = rows.where("not held_out")
    size = coder(model).get_piece_size()
    initial = np.array([coder(model).id_to_piece(i).startswith("▁") for i in range(size)])
    words = C.cut(word_counts(train), "words")
    total, kinds, once, twice = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*"), F.count_if(F.col("n") == 1), F.count_if(F.col("n") == 2)).first()
    # each word's own occurrence left out, this share of one is what words lose to those not seen
    discount = min(DISCOUNTS, key=lambda x: abs(x - (once / (once + 2 * twice) if once else 0.5)))
    hot = words.where((F.length("word") <= LONG) & (F.length("word") > 0)).orderBy(F.desc("n"), "word").limit(HOT).toArrow()
    ends = words.where(F.length("word") == 0).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    names, often = hot["word"].to_pylist(), hot["n"].to_numpy().astype(float)
    known, table = {w: i for i, w in enumerate(names)}, Spelled(names, model)
    # the frequent words say which ids get classes, rows and columns of their own; the counts of all words fill these
    some = np.bincount(table.flat, np.repeat(often, table.lengths), size).astype(np.int64)
    some[END] += ends
    net = learnt(train, laid_out(some, initial, company_of(train, some, model, known, table)), model, known, table)
    place = np.where(net.column < COLUMNS, net.column, COLUMNS + net.cls)
    pairs = pair_counts(words, model, net.row, place).toArrow()
    alone = pc.less(pairs["row"], 0)
    by, ids = np.zeros((3, size), np.int64), pairs.filter(alone)
    by[-1 - ids["row"].to_numpy(), ids["column"].to_numpy()] = ids["n"].to_numpy()
    inside = within(net, pairs.filter(pc.invert(alone)), by[0])
    # of each class, the words that begin in it and how many distinct ones there are; a class of none leaves all to the ids
    kinds_in, words_in = (np.bincount(net.cls[:size], x, CLASSES) for x in by[1:])
    words_in, kinds_in = np.where(words_in > 0, words_in, 1.0), np.where(words_in > 0, kinds_in, np.inf)
    begins = np.bincount(net.cls[:size], initial, CLASSES) > 0
    begins[net.cls[END]] = True
    shared = spark.sparkContext.broadcast((net, inside, known, often, table))
    floor = float(np.log10(total + kinds + 1))

    def counts_of(part: Slice, often: np.ndarray) -> np.ndarray:
        counts = np.where(part.place >= 0, often[part.place] if len(often) else 0.0, 0.0)
        counts[0] = ends
        return counts[part.index]

    def chances(counts: np.ndarray, cls: np.ndarray, spelled: np.ndarray, discount: float) -> tuple[np.ndarray, np.ndarray]:
        """log10 chance of words in their classes, and the part of it that comes from their ids."""
        left = spelled + np.log10(np.minimum(1.0, discount * kinds_in / words_in))[cls]
        with np.errstate(divide="ignore"):
            return log_sum(np.log10(np.maximum(0, counts - discount) / words_in[cls]), left), left

    def make():
        net, inside, known, often, table = shared.value

        def each(batch: pa.RecordBatch) -> dict:
            part = Slice(batch["text"].to_pylist(), model, known, table)
            (heads, spelled), counts, cls = spelled_logs(net, inside, begins, part), counts_of(part, often), net.cls[part.ids[part.at]]
            mixed, spelled = chances(counts, cls, spelled, discount)
            mixed += heads
            one = 1 / words_in[cls]
            start = np.concatenate([[0], part.ends[:-1]])
            n = part.ends - start
            n_known, base, score = (np.add.reduceat(x, start) for x in ((counts > 0).astype(np.int64), np.log10(counts + 1), mixed))
            open_ = np.flatnonzero((counts == 0) & (part.index > 0))
            bounds = np.searchsorted(open_, part.ends).tolist()
            left = [{"key": key_of(part.words[i]), "s": s, "one": x} for i, s, x in zip(part.index[open_].tolist(), spelled[open_].tolist(), one[open_].tolist(), strict=True)]
            return {c: batch[c] for c in ("rid", "doc_id", "held_out")} | {"n_tokens": n, "n_known": n_known, "base": base, "score": score, "rare": [left[a:b] for a, b in zip([0, *bounds[:-1]], bounds, strict=True)]}

        return each

    scored = C.cut(C.map_rows(rows, make, "rid long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, score double, rare array<struct<key:binary,s:double,one:double>>"), "scored")
    # words outside the table get their counts, and their share of the class, by a join; no key of it is hot but long words, which go by broadcast
    rare = scored.select("rid", F.explode("rare").alias("x")).select("rid", "x.key", "x.s", "x.one")
    met = C.join_on_key(rare, words.select(key_column().alias("key"), "n", F.col("n").alias("times")), ["key"], "times", total)
    gain = F.log10((F.col("n") - F.lit(discount)) * F.col("one") + F.pow(F.lit(10.0), "s")) - F.col("s")
    more = met.groupBy("rid").agg(F.count("*").alias("k"), F.sum(F.log10(F.col("n") + 1)).alias("l"), F.sum(gain).alias("g"))
    out = scored.drop("rare").join(more, "rid", "left")
    added = lambda c: F.coalesce(c, F.lit(0.0))
    return out.select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("k", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"), (F.col("base") + added("l") - F.col("n_tokens") * floor).alias("base_score"), (F.col("score") + added("g")).alias("score"))


def op4_attention_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_all(C.documents(spark, sf_dir))


QUERIES = {"op4_attention_lm": op4_attention_lm}
ORACLES: dict[str, str] = {}
