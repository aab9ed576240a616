"""Toxicity by multiple-instance learning.

A document is a bag of sentences of which only the bag is labelled.  Each
sentence has a logistic score over its words; the scores are combined by a leaky
noisy-or, 1 - (1 - leak) * prod(1 - p), and trained from the document labels,
so the gradient finds the sentences that explain a toxic label.  Words count by
themselves, their beginnings and their inner runs, as insults are inflected.  The
same sentence scores then locate the offending sentences.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from math import exp, log1p

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

#: Most labelled documents used to fit the classifier, chosen by a hash of their id.
SAMPLE = 6_000
ROUNDS = 80
#: Words whose summed weight a task remembers.
MEMO = 150_000
ENDS = re.compile(rb"[.!?\n]+")
STRIP = b".,;:!?()[]{}\"'|*#$%&_-"


def features(word: bytes) -> set[bytes]:
    """The word itself, its beginnings of 3 to 8 characters and the runs of 5 within its bounds."""
    text = word.decode("utf-8", "replace")
    found = {("=" + text).encode()} | {("^" + text[:n]).encode() for n in range(3, 9) if n < len(text)}
    edged = f"<{text}>"
    return found | {edged[i : i + 5].encode() for i in range(len(edged) - 4)}


def bags_of(text: bytes) -> list[set[bytes]]:
    """The distinct words of each sentence that has any."""
    parts = ({w for x in part.split() if (w := x.strip(STRIP))} for part in ENDS.split(text.lower()))
    return [x for x in parts if x]


def words_of(text: bytes) -> set[bytes]:
    return {w for x in text.lower().split() for y in ENDS.split(x) if (w := y.strip(STRIP))}


class Lookup(dict):
    """The features of a word that are known, bounded."""

    def __init__(self, known: dict):
        self.known = known

    def __missing__(self, word: bytes) -> tuple[bytes, ...]:
        if len(self) >= MEMO // 2:
            self.clear()
        x = self[word] = tuple(f for f in features(word) if f in self.known)
        return x


@dataclass
class Model:
    """Weights of word features, a sentence's bias and the chance of a toxic document without an offending sentence."""

    weights: dict[bytes, float]
    bias: float
    leak: float
    memo: dict[bytes, float] = field(default_factory=dict)

    def word(self, token: bytes) -> float:
        """The summed weight of one token, remembered."""
        if (x := self.memo.get(token)) is None:
            get = self.weights.get
            x = sum(v for f in features(token.strip(STRIP)) if (v := get(f)) is not None) if self.weights else 0.0
            if len(self.memo) >= MEMO:
                self.memo.clear()
            self.memo[token] = x
        return x

    def chance(self, z: float) -> float:
        return 1 / (1 + exp(-min(30.0, max(-30.0, self.bias + z))))

    def sentence(self, words: list[bytes]) -> float:
        return self.chance(sum(self.word(w) for w in {w.strip(STRIP) for w in words}))

    def score(self, text: bytes) -> float:
        stay, plain, memo, word = log1p(-self.leak), log1p(-self.chance(0.0)), self.memo, self.word
        for part in ENDS.split(text.lower()):
            told = []
            for w in set(part.split()):
                x = memo.get(w)
                if x is None:
                    x = word(w)
                if x:
                    told.append((w, x))
            # as in training, a word counts once however it is punctuated
            z = sum({w.strip(STRIP): x for w, x in told}.values()) if len(told) > 1 else told[0][1] if told else 0.0
            stay += log1p(-self.chance(z)) if z else plain
        return min(1.0, max(0.0, 1 - exp(stay)))

    def located(self, text: bytes) -> list[tuple[int, int, float]]:
        """(start, end, score) in bytes of each sentence that has a word."""
        out, at = [], 0
        for m in [*ENDS.finditer(text), None]:
            end = m.start() if m else len(text)
            if w := text[at:end].lower().split():
                out.append((at, end, self.sentence(w)))
            at = m.end() if m else end
        return out


def fit(texts: list[bytes], toxic: list[int], rounds: int = ROUNDS, ratio: float = 6.0, ridge: float = 1e-5, rate: float = 0.2) -> Model:
    """Noisy-or likelihood by Adam over the features that toxic documents hold ``ratio`` times as often as others."""
    y = np.array(toxic, float)
    if not len(y) or not y.any():
        return Model({}, -12.0, 1e-3)
    n, least = (len(y) - y.sum() + 1, y.sum() + 1), 5 if y.sum() >= 200 else 3
    # only what recurs in toxic documents is ever counted in the others, so memory stays with the few
    toxic_n: dict[bytes, int] = {}
    for text in (t for t, k in zip(texts, toxic, strict=True) if k):
        for f in set().union(*map(features, words_of(text))):
            toxic_n[f] = toxic_n.get(f, 0) + 1
    toxic_n = {f: a for f, a in toxic_n.items() if a >= least}
    look, other_n = Lookup(toxic_n), dict.fromkeys(toxic_n, 0)
    for text in (t for t, k in zip(texts, toxic, strict=True) if not k):
        for f in {f for w in words_of(text) for f in look[w]}:
            other_n[f] += 1
    chosen = sorted(f for f, a in toxic_n.items() if (a + 0.5) / n[1] >= ratio * (other_n[f] + 0.5) / n[0])
    vocab = {f: i for i, f in enumerate(chosen)}
    look, doc, word, sent = Lookup(vocab), [], [], []
    for d, text in enumerate(texts):
        for part in bags_of(text) or [set()]:
            ids = [vocab[f] for w in part for f in look[w]]
            word += ids
            sent += [len(doc)] * len(ids)
            doc.append(d)
    doc = np.array(doc, np.int64)
    word, sent = np.array(word, np.int64), np.array(sent, np.int64)
    theta = np.concatenate([np.zeros(len(vocab)), [-7.0, -3.0]])  # features, bias, leak's logit
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for t in range(1, rounds + 1):
        z = theta[-2] + np.bincount(sent, theta[:-2][word], len(doc))
        p = np.clip(1 / (1 + np.exp(-np.clip(z, -30, 30))), 1e-12, 1 - 1e-9)
        leak = 1 / (1 + np.exp(-theta[-1]))
        clean = np.exp(np.log1p(-leak) + np.bincount(doc, np.log1p(-p), len(y)))
        pull = np.where(y == 1, -clean / np.maximum(1 - clean, 1e-9), 1.0)  # d loss / d log-odds, over p
        dz = pull[doc] * p
        grad = np.concatenate([np.bincount(word, dz[sent], len(vocab)) / len(y) + ridge * theta[:-2], [dz.mean() / len(y) * len(dz), (pull * leak).mean()]])
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-7)
        theta[-2:] = np.minimum(theta[-2:], [-5.0, -1.5])
    return Model({w: float(theta[i]) for w, i in vocab.items()}, float(theta[-2]), float(1 / (1 + np.exp(-theta[-1]))))


def remainder(column: str, mod: int) -> Column:
    return F.crc32(F.col(column).cast("string").cast("binary")) % mod


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Fits on at most ``sample`` labelled rows outside the held-out fold; ids are chosen before texts are read."""
    ids = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    ids = ids.where(remainder("doc_id", 5) != 0).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = docs.select("doc_id", C.text_bytes().alias("text")).join(F.broadcast(ids), "doc_id").select("doc_id", "text", "toxic").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["text"]))
    return fit([bytes(r["text"]) for r in rows], [int(r["toxic"] == 1) for r in rows])


def scored(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """(doc_id, score, n_offending, worst_start, worst_end) of every row.

    Null and empty texts get the leak; long texts are read whole; equal texts
    score alike, so ties and repeated rows get a row each; an empty table gives
    none; other columns are ignored.  In texts of ``least`` or more the sentences
    that reach ``least`` are counted and the worst is located by byte offsets.
    """

    def make():
        def each(batch: pa.RecordBatch) -> dict:
            out: dict[str, list] = {"score": [], "n_offending": [], "worst_start": [], "worst_end": []}
            for text in batch["text"].to_pylist():
                score = model.score(text)
                where = [x for x in model.located(text) if x[2] >= least] if score >= least else []
                worst = max(where, key=lambda x: (x[2], -x[0]), default=(None, None))
                for k, v in zip(out, (score, len(where), *worst[:2]), strict=True):
                    out[k].append(v)
            return {"doc_id": batch["doc_id"]} | out

        return each

    return C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), make, "doc_id long, score double, n_offending long, worst_start long, worst_end long")


def offending(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """(doc_id, start, end, score, sentence): sentences that score ``least`` or more, by byte offsets."""

    def make():
        def each(batch: pa.RecordBatch) -> dict | None:
            out = [(d, s, e, p, x[s:e].decode("utf-8", "replace")) for d, x in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True) for s, e, p in model.located(x) if p >= least]
            return {n: [x[i] for x in out] for i, n in enumerate(("doc_id", "start", "end", "score", "sentence"))} if out else None

        return each

    return C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), make, "doc_id long, start long, end long, score double, sentence string")


def clean(docs: DataFrame, labels: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows that score under ``least``, with their columns as they are."""
    model, names = train(docs, labels), docs.columns

    @F.pandas_udf("double")
    def score(text):
        return text.map(model.score)

    own = C.free(docs, "_score")
    return docs.withColumn(own, score(C.text_bytes())).where(F.col(own) < least).select(*names)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.documents(spark, sf_dir)
    found = scored(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return found.select("doc_id", (remainder("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_offending", "worst_start", "worst_end")


QUERIES = {"op2_toxicity": op2_toxicity}
ORACLES: dict[str, str] = {}
