"""Space and time of the search for repeated strings: shuffles are cleared as it goes, and strings are compared by runs."""

import glob
import os
import random
import tempfile
import time

import numpy as np
import pytest

from hybridrange.llm import suffix_dedup


def shuffled(spark):
    """Bytes in the files of shuffles that the session still holds."""
    places = spark.conf.get("spark.local.dir", None) or os.environ.get("SPARK_LOCAL_DIRS") or tempfile.gettempdir()
    total = 0
    for f in (f for d in places.split(",") for f in glob.glob(f"{d}/**/blockmgr-*/*/shuffle_*.data", recursive=True)):
        try:
            total += os.path.getsize(f)
        except FileNotFoundError:  # deleted meanwhile
            pass
    return total


def test_no_shuffle_outlives_its_table(spark):
    r = random.Random(4)
    text = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    passage = text(900)
    d = spark.createDataFrame([(i, (text(3000) + passage * (i % 3 == 0)).encode()) for i in range(300)], "rid long, text binary").repartition(3)
    before, parts = shuffled(spark), suffix_dedup.C.width(spark)
    runs = suffix_dedup.repeated_starts(d)
    until = time.time() + 10
    while shuffled(spark) - before > 1000 * parts and time.time() < until:
        time.sleep(0.2)
    assert shuffled(spark) - before <= 1000 * parts  # those of a count at most
    assert runs.select("rid").distinct().count() == 100


@pytest.mark.parametrize("chance", [False, True])
def test_strings_are_compared_by_runs(monkeypatch, chance):
    if chance:  # every hash meets every other one
        monkeypatch.setattr(suffix_dedup, "gram_hashes", lambda b, k: np.zeros(len(b) - k + 1, np.uint64))
    r = random.Random(2)
    for _ in range(50):
        raw = bytes(r.choice(b"ab") for _ in range(40)) * 2 + bytes(r.choice(b"ab") for _ in range(60))
        x, y = (np.array([r.randrange(len(raw) - 12) for _ in range(80)]) for _ in range(2))
        got = suffix_dedup.same_strings(raw, x, y, 12).tolist()
        assert got == [raw[i : i + 12] == raw[j : j + 12] for i, j in zip(x.tolist(), y.tolist(), strict=True)]


def test_spans_by_part():
    hits = [np.array(x, bool) for x in ([1, 1], [], [0, 1, 0, 1, 1], [1], [0])]
    assert suffix_dedup.spans(hits) == [[(0, 1)], [], [(1, 1), (3, 4)], [(0, 0)], []]
    assert suffix_dedup.spans([]) == []


def test_words_are_told_by_their_bytes():
    r = random.Random(3)
    words = [bytes(r.choice(b"abc\xe4") for _ in range(r.randint(1, 5))) for _ in range(500)]
    h = suffix_dedup.word_hashes(b" \t" + b"\x0b\n ".join(words))
    assert len(h) == 500 and len(set(h.tolist())) == len(set(words)) == len(set(zip(words, h.tolist(), strict=True)))
    assert len(suffix_dedup.word_hashes(b"")) == len(suffix_dedup.word_hashes(b" \n")) == 0
