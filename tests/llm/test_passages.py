"""Documents that share passages of over 50 words, against brute force."""

import random

import pytest

from hybridrange.llm import suffix_dedup


@pytest.mark.parametrize("partitions", [1, 3])
def test_every_passage_of_over_fifty_words_is_marked(spark, partitions):
    r = random.Random(9)
    words = lambda n: [f"w{r.randrange(4000)}" for _ in range(n)]
    texts = [words(r.randint(0, 300)) for _ in range(120)]
    for n in (20, 30, 36, 51, 52, 55, 59, 80):
        passage = words(n)
        for i in r.sample(range(len(texts)), 3):
            at = r.randint(0, len(texts[i]))
            texts[i] = texts[i][:at] + passage + texts[i][at:]
    again = words(70)
    texts += [again + words(5) + again, [], words(51)]  # a passage that one text repeats is not shared
    texts.append(list(texts[-1]))
    shared = {}
    for n in (51, suffix_dedup.WORDS + suffix_dedup.COVERED * suffix_dedup.STEP):
        at = {}
        for i, w in enumerate(texts):
            for j in range(len(w) - n + 1):
                at.setdefault(tuple(w[j : j + n]), set()).add(i)
        shared[n] = {i for x in at.values() if len(x) > 1 for i in x}
    sure, may = shared.values()
    d = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)] + [(999, None)], "doc_id long, text string").repartition(partitions)
    got = {x.doc_id for x in suffix_dedup.remove_repeats(d).collect() if x.n_shared}
    assert len(sure) > 10 and sure <= got <= may
