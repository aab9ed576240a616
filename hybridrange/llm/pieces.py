"""SentencePiece encoding and decoding by a max-plus parallel scan.

The pieces of a public model (of merges, so its scores are ranks) get additive
integer scores by rank, and a text's
encoding is the segmentation of greatest score, on ties with the longest last
piece.  No piece has a word mark after another character, so a text falls into
units (word marks and what follows) that are solved apart and remembered.  A
giant document is split into chunks wherever the count of characters says: each
chunk yields the max-plus matrix of its boundary states, matrices are combined
associatively in blocks, entry scores flow left to right, the map from exit to
entry states flows right to left, and each chunk is backtraced by itself.
"""

from __future__ import annotations

import hashlib
import os
import re
from array import array
from itertools import chain
from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

#: The model file; a parameter of every function, never copied.
MODEL = os.environ.get("PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")
#: Code points of a chunk; longer documents are split.
CHUNK = 32_768
#: Chunks or blocks that one step of a scan combines.
FAN = 64
#: Units that a process remembers.
MEMO = 800_000
MARK = "▁"
#: Stands for a literal word mark: a lone surrogate, which no text in UTF-8 holds.
STAND = "\ud800"
NONE = -(2**60)
#: Word marks with what follows them; no piece holds a line feed, so it stands alone.
UNIT = re.compile(f"{MARK}*[^{MARK}\n]+|{MARK}+|\n")


class Pieces:
    """Scores and ids of a model's pieces, and the automaton that finds them all in a text."""

    def __init__(self, model: str = MODEL):
        import ahocorasick
        import sentencepiece

        coder = sentencepiece.SentencePieceProcessor(model_file=model)
        size = coder.get_piece_size()
        self.texts = [coder.id_to_piece(i) for i in range(size)]
        low = {i: int(self.texts[i][3:5], 16) for i in range(size) if coder.is_byte(i)}
        self.byte_id = {b: i for i, b in low.items()}
        plain = [i for i in range(size) if i not in low and not coder.is_control(i) and not coder.is_unknown(i)]
        total = sum(1 / r for r in range(1, len(plain) + 1))
        self.ids = {self.texts[p]: p for p in plain}
        self.score = {self.texts[p]: round(-1e6 * log(r * total)) for r, p in enumerate(plain, 1)}
        self.fall = min(self.score.values()) - 10_000_000  # a byte of a character without piece
        self.reach = max(map(len, self.score))
        self.spelling = [bytes([low[i]]) if i in low else t.replace(MARK, " ").encode() for i, t in enumerate(self.texts)]
        self.finder = ahocorasick.Automaton()
        for t, s in self.score.items():
            self.finder.add_word(t, (len(t), s))
        self.finder.make_automaton()
        self.memo: dict[str, tuple[int, ...]] = {}

    def solve(self, text: str, entry: list[int], stop: int, apart: bool = False) -> tuple[list[int], list[int]]:
        """Best scores and last piece lengths at every place of ``text``; pieces start before ``stop``.

        ``entry[i]`` is the score of reaching place i from outside, NONE if none
        does.  With ``apart`` a line feed starts anew.
        """
        n, score = len(text), self.score
        best = [NONE] * (n + 1)
        best[: len(entry)] = entry[: n + 1]
        last = [0] * (n + 1)
        bare = [i for i, c in enumerate(text) if c not in score]  # characters that may have to be spelled in bytes
        bare.append(n)
        k = 0
        # matches come by their ends, the longest first, so of equal scores the longest last piece stays
        for end, (size, s) in self.finder.iter(text):
            while bare[k] < end:
                self.fallen(text, bare[k], best, last, stop, apart)
                k += 1
            at = end + 1 - size
            if at < stop and (v := best[at] + s) > best[end + 1] and v > NONE:
                best[end + 1] = v
                last[end + 1] = size
        for i in bare[k:-1]:
            self.fallen(text, i, best, last, stop, apart)
        return best, last

    def fallen(self, text: str, i: int, best: list[int], last: list[int], stop: int, apart: bool) -> None:
        """A character without a piece of its own."""
        if apart and text[i] == "\n":
            best[i + 1] = 0
        elif i < stop and best[i] > NONE and (v := best[i] + self.fall * len(self.raw(text[i]))) > best[i + 1]:
            best[i + 1], last[i + 1] = v, 1

    def spelled(self, piece: str) -> tuple[int, ...]:
        p = self.ids.get(piece)
        return (p,) if p is not None else tuple(self.byte_id[b] for b in self.raw(piece))

    def raw(self, piece: str) -> bytes:
        """Bytes of a character without piece; the stand-in is spelled as the word mark itself."""
        return piece.replace(STAND, MARK).encode("utf-8", "surrogatepass")

    def learn(self, units: set[str]) -> None:
        """Solves the units that aren't remembered, all in one pass."""
        new = [u for u in units if u not in self.memo]
        if not new:
            return
        if len(self.memo) + len(new) > MEMO:
            self.memo.clear()
            new = list(units)
        if "\n" in new:
            new.remove("\n")
            self.memo["\n"] = self.spelled("\n")
        text = "\n".join(new)
        _, last = self.solve(text, [0], len(text), apart=True)
        end, ids, spelled, memo = 0, self.ids.get, self.spelled, self.memo
        for unit in new:
            start, end = end, end + len(unit)
            at, out = end, []
            while at > start:
                size = last[at]
                piece = text[at - size : at]
                p = ids(piece)
                if p is not None:
                    out.append(p)
                else:
                    out += reversed(spelled(piece))
                at -= size
            out.reverse()
            memo[unit] = tuple(out)
            end += 1

    def plain(self, text: str) -> list[int]:
        """Ids of a text whose spaces are word marks."""
        units = UNIT.findall(text)
        self.learn(set(units))
        return list(chain.from_iterable(map(self.memo.__getitem__, units)))

    def encode(self, text: str) -> list[int]:
        """Ids of a whole text; literal word marks are spelled in bytes."""
        return self.plain(marked(text))

    def encode_all(self, texts: list[str]) -> list[list[int]]:
        """Ids of several texts, whose new units are solved together."""
        units = [UNIT.findall(marked(x)) for x in texts]
        self.learn(set(chain.from_iterable(units)))
        get = self.memo.__getitem__
        return [list(chain.from_iterable(map(get, u))) for u in units]

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.spelling.__getitem__, ids)).decode("utf-8", "surrogatepass")

    def cuts(self, text: str, size: int) -> tuple[int, int] | None:
        """The first and last place that every segmentation cuts, of those that no state at the borders reaches."""
        found = [m.start() for m in UNIT.finditer(text) if self.reach <= m.start() < size]
        return (found[0], found[-1]) if found else None

    def matrix(self, text: str, size: int) -> np.ndarray:
        """Best scores from entering at place i (row) to leaving at place size + j (column), of pieces that start before ``size``.

        What lies between the first and the last forced cut is common to all ways
        and is left out: it changes no choice.
        """
        cuts = self.cuts(text, size)
        first, final = cuts or (len(text), 0)
        out = np.full((self.reach, self.reach), NONE, np.int64)
        if cuts:
            tail = self.solve(text[final:], [0], size - final)[0]
        for i in range(min(self.reach, len(text) + 1)):
            if i >= size:  # a chunk shorter than a piece is passed over
                if i - size < self.reach:
                    out[i, i - size] = 0
                continue
            head = self.solve(text[:first], [NONE] * i + [0], min(first, size))[0]
            for j in range(self.reach):
                if (at := size + j) <= len(text):
                    out[i, j] = head[at] if not cuts else head[first] + tail[at - final] if tail[at - final] > NONE and head[first] > NONE else NONE
        return np.maximum(out, NONE)

    def entries(self, text: str, size: int, entry: list[int]) -> np.ndarray:
        """For each exit state the entry state of the best way; where the chunk is cut it is the same for all."""
        cuts = self.cuts(text, size)
        head = text[: cuts[0]] if cuts else text
        _, last = self.solve(head, entry, min(size, len(head)))
        out = np.zeros(self.reach, np.int64)
        for j in range(self.reach):
            at = cuts[0] if cuts else size + j
            if at <= len(text):
                while last[at]:
                    at -= last[at]
                out[j] = at if at < self.reach else 0  # no way leads to that exit
        return out

    def chunk(self, text: str, size: int, entry: list[int], leave: int) -> list[int]:
        """Ids of a chunk from its entry state to its exit."""
        cuts = self.cuts(text, size)
        if not cuts:
            return self.backtrace(text, self.solve(text, entry, size)[1], size + leave)
        first, final = cuts
        head = self.backtrace(text, self.solve(text[:first], entry, first)[1], first)
        tail = self.backtrace(text[final:], self.solve(text[final:], [0], size - final)[1], size + leave - final)
        return head + self.plain(text[first:final]) + tail

    def backtrace(self, text: str, last: list[int], at: int) -> list[int]:
        out: list[tuple[int, ...]] = []
        while last[at]:
            out.append(self.spelled(text[at - last[at] : at]))
            at -= last[at]
        return list(chain.from_iterable(reversed(out)))


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Max-plus product."""
    return np.maximum((a[:, :, None] + b[None, :, :]).max(1), NONE)


_LOADED: dict[str, Pieces] = {}


def loaded(model: str) -> Pieces:
    """The pieces of a model, read once in a process."""
    if model not in _LOADED:
        _LOADED[model] = Pieces(model)
    return _LOADED[model]


def marked(text: str) -> str:
    """A giant text's spaces as word marks, and its literal word marks as a character that no piece has."""
    return text.replace(MARK, STAND).replace(" ", MARK)


def scan(parts: DataFrame, model: str) -> DataFrame:
    """(rid, c, entry): the scores at which every chunk's first places are reached, by blocks of FAN matrices."""
    reach = loaded(model).reach
    parts = C.cut(parts, "matrices")
    levels = [parts]
    while (levels[-1].agg(F.max("c")).first()[0] or 0) >= FAN:

        def block(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
            product = None
            for x in rows.sort_by("c")["m"].to_pylist():
                one = np.frombuffer(x, np.int64).reshape(reach, reach)
                product = one if product is None else times(product, one)
            return pa.table({"rid": pa.array([key[0].as_py()], pa.int64()), "c": pa.array([key[1].as_py()], pa.int64()), "m": pa.array([product.tobytes()], pa.binary())})

        levels.append(C.cut(levels[-1].groupBy("rid", F.floor(F.col("c") / FAN).alias("b")).applyInArrow(block, "rid long, c long, m binary"), "matrices"))
    start = np.full(reach, NONE, np.int64)
    start[0] = 0
    entries = None
    for level in reversed(levels):

        def walk(rows: pa.Table) -> pa.Table:
            rows = rows.sort_by("c")
            given = rows["entry"][0].as_py()
            v, out = np.frombuffer(given, np.int64) if given is not None else start, []
            for x in rows["m"].to_pylist():
                out.append(v.tobytes())
                v = np.maximum((v[:, None] + np.frombuffer(x, np.int64).reshape(reach, reach)).max(0), NONE)
            return pa.table({"rid": rows["rid"], "c": rows["c"], "entry": pa.array(out, pa.binary())})

        keyed = level.withColumn("b", F.floor(F.col("c") / FAN))
        keyed = keyed.join(entries.withColumnRenamed("c", "b"), ["rid", "b"]) if entries is not None else keyed.withColumn("entry", F.lit(None).cast("binary"))
        entries = keyed.groupBy("rid", "b").applyInArrow(walk, "rid long, c long, entry binary")
    return entries


def exits(maps: DataFrame, model: str) -> DataFrame:
    """(rid, c, leave): the place beyond each chunk's end at which the best segmentation of the whole leaves it.

    ``maps(rid, c, f, last)`` has for every exit state its entry state; ``last``
    marks a document's final chunk, which is left at its end.
    """
    maps = C.cut(maps, "maps")
    levels = [maps]
    while (levels[-1].agg(F.max("c")).first()[0] or 0) >= FAN:

        def block(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
            product = None
            for x in rows.sort_by([("c", "descending")])["f"].to_pylist():
                one = np.frombuffer(x, np.int64)
                product = one if product is None else one[product]
            return pa.table({"rid": pa.array([key[0].as_py()], pa.int64()), "c": pa.array([key[1].as_py()], pa.int64()), "f": pa.array([product.tobytes()], pa.binary())})

        levels.append(C.cut(levels[-1].groupBy("rid", F.floor(F.col("c") / FAN).alias("b")).applyInArrow(block, "rid long, c long, f binary"), "maps"))
    leaves = None
    for level in reversed(levels):

        def walk(rows: pa.Table) -> pa.Table:
            rows = rows.sort_by([("c", "descending")])
            at, out = rows["leave"][0].as_py() or 0, []
            for x in rows["f"].to_pylist():
                out.append(at)
                at = int(np.frombuffer(x, np.int64)[at])
            return pa.table({"rid": rows["rid"], "c": rows["c"], "leave": pa.array(out, pa.int64())})

        keyed = level.withColumn("b", F.floor(F.col("c") / FAN))
        keyed = keyed.join(leaves.withColumnRenamed("c", "b"), ["rid", "b"]) if leaves is not None else keyed.withColumn("leave", F.lit(0).cast("long"))
        leaves = keyed.groupBy("rid", "b").applyInArrow(walk, "rid long, c long, leave long")
    return leaves


def chunks_of(docs: DataFrame, model: str, chunk: int) -> DataFrame:
    """Chunks of giant texts with the characters that their last pieces may reach into."""

    def make():
        reach = loaded(model).reach

        def each(batch: pa.RecordBatch) -> dict | None:
            out: dict[str, list] = {"rid": [], "c": [], "size": [], "text": []}
            for rid, text in zip(batch["rid"].to_pylist(), batch["text"].to_pylist(), strict=True):
                for c, at in enumerate(range(0, len(text), chunk)):
                    for k, v in zip(out, (rid, c, min(chunk, len(text) - at), text[at : at + chunk + reach - 1]), strict=True):
                        out[k].append(v)
            return out if out["rid"] else None

        return each

    return C.map_rows(docs.select("rid", "text"), make, "rid long, c long, size int, text string")


def encode_giants(giants: DataFrame, model: str, chunk: int) -> DataFrame:
    """(rid, ids) of giant texts, by chunks."""
    parts = C.cut(chunks_of(giants, model, chunk), "chunks")

    def matrices():
        pieces = loaded(model)

        def each(batch: pa.RecordBatch) -> dict:
            return {"rid": batch["rid"], "c": batch["c"], "m": [pieces.matrix(marked(t), n).tobytes() for t, n in zip(batch["text"].to_pylist(), batch["size"].to_pylist(), strict=True)]}

        return each

    ways = scan(C.map_rows(parts, matrices, "rid long, c long, m binary"), model)
    entered = C.cut(parts.join(ways, ["rid", "c"]), "entered")

    def mapped():
        pieces = loaded(model)

        def each(batch: pa.RecordBatch) -> dict:
            rows = zip(*(batch[c].to_pylist() for c in ("text", "size", "entry")), strict=True)
            return {"rid": batch["rid"], "c": batch["c"], "f": [pieces.entries(marked(t), n, np.frombuffer(e, np.int64).tolist()).tobytes() for t, n, e in rows]}

        return each

    def traced():
        pieces = loaded(model)

        def each(batch: pa.RecordBatch) -> dict:
            rows = zip(*(batch[c].to_pylist() for c in ("text", "size", "entry", "leave")), strict=True)
            return {"rid": batch["rid"], "c": batch["c"], "ids": [pieces.chunk(marked(t), n, np.frombuffer(e, np.int64).tolist(), x) for t, n, e, x in rows]}

        return each

    left = exits(C.map_rows(entered, mapped, "rid long, c long, f binary"), model)
    found = C.map_rows(entered.join(left, ["rid", "c"]), traced, "rid long, c long, ids array<int>")
    return found.groupBy("rid").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("c", "ids"))), lambda x: x["ids"])).alias("ids"))


RESULT = "doc_id long, ids array<int>, decoded string, exact boolean"
DIGEST = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, exact boolean"


def encode(docs: DataFrame, model: str = MODEL, chunk: int = CHUNK, digest: bool = False) -> DataFrame:
    """(doc_id, ids, decoded, exact) of every row; ``exact`` tells that decoding gives the text back.

    With ``digest`` the ids and the decoded text are given as SHA-256 (ids as
    32-bit numbers).  Null counts as empty and has no ids; rows that
    repeat a doc_id are encoded each; an empty table gives no rows; documents
    longer than ``chunk`` code points go through the parallel scan.
    """
    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", text.alias("text"))

    def finished(ids_given: bool):
        def make():
            pieces = loaded(model)

            def each(batch: pa.RecordBatch) -> dict:
                texts = batch["text"].to_pylist()
                ids = batch["ids"].to_pylist() if ids_given else pieces.encode_all(texts)
                back = [pieces.decode(x) for x in ids]
                out = {"doc_id": batch["doc_id"], "exact": [a == b for a, b in zip(texts, back, strict=True)]}
                if not digest:
                    return out | {"ids": ids, "decoded": back}
                sha = lambda x: hashlib.sha256(x).hexdigest()
                return out | {"n_tokens": list(map(len, ids)), "ids_sha256": [sha(array("i", x).tobytes()) for x in ids], "decoded_sha256": [sha(x.encode("utf-8", "surrogatepass")) for x in back]}

            return each

        return make

    result = DIGEST if digest else RESULT
    small = C.map_rows(rows.where(F.length("text") <= chunk).select("doc_id", "text"), finished(False), result)
    giants = C.cut(rows.where(F.length("text") > chunk), "giants")
    large = C.map_rows(giants.join(encode_giants(giants, model, chunk), "rid").select("doc_id", "text", "ids"), finished(True), result)
    return small.union(large)


def op5_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(C.documents(spark, sf_dir), digest=True)


QUERIES = {"op5_pieces": op5_pieces}
ORACLES: dict[str, str] = {}
