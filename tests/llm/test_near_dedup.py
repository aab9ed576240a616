"""The pipeline's near-dedup against brute-force Jaccard similarity."""

import random

import pytest

from hybridrange.llm import simhash
from tests.llm.test_operators import linked


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def jaccard(x, y):
    return len(x & y) / len(x | y) if x or y else 1.0


def near_texts(r):
    out = []
    for edits in (1, 2, 3, 4, 5, 6, 7, 8, 10, 12):  # Jaccard similarities from 0.95 down to about 0.55
        for _ in range(6):
            base = ["".join(r.choice("abcdefghij") for _ in range(6)) for _ in range(200)]
            out.append(" ".join(base))
            for at in r.sample(range(200), edits):
                base[at] = f"edit{r.random()}"
            out.append(" ".join(base))
    hub = [f"w{r.randrange(10**6)}" for _ in range(150)]
    for _ in range(25):  # one family, of pairs on both sides of the threshold
        w = list(hub)
        for at in r.sample(range(150), r.randint(1, 5)):
            w[at] = f"own{r.random()}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("block", [4, 256])
def test_near_dedup_agrees_with_brute_force(spark, block):
    r = random.Random(21)
    texts = dict(enumerate(near_texts(r)))
    texts |= {1000: None, 1001: "", 1002: "One two", 1003: "one TWO", 1004: "one two three"}
    s = {i: shingles(t or "") for i, t in texts.items()}
    pairs = [(a, b) for a in s for b in s if a < b and jaccard(s[a], s[b]) >= 0.8]
    unverified = [(a, b) for a in s for b in s if a < b and 0.6 <= jaccard(s[a], s[b]) < 0.8]
    assert len(pairs) > 30 and len(unverified) > 30
    d = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    assert {x.doc_id: x.component_id for x in simhash.alike_groups(d, block=block).collect()} == linked(s, pairs)
    assert {x.doc_id for x in simhash.dedup(d).collect()} == set(linked(s, pairs).values())
    assert simhash.dedup(d.limit(0)).count() == 0
