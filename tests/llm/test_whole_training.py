"""The attention model, its classes and its discount are learnt from every word of every training text."""

import numpy as np

from hybridrange.llm import attention_lm as A


def test_every_word_of_every_text_is_learnt_from(spark):
    texts = [b" ".join(b"w%d" % ((i * j) % 23) for j in range(40 + i)) for i in range(30)]
    words = sorted({w for x in texts for w in x.split()})
    known, table = {w: i for i, w in enumerate(words)}, A.Spelled(words, A.MODEL)
    size = A.coder(A.MODEL).get_piece_size()
    initial = np.array([A.coder(A.MODEL).id_to_piece(i).startswith("▁") for i in range(size)])
    seen = np.bincount(table.flat, minlength=size)
    train = spark.createDataFrame([(i, bytearray(x)) for i, x in enumerate(texts)], "doc_id long, text binary").repartition(3)
    every = A.Slice(texts, A.MODEL, known, table).texts
    net = A.learnt(train, A.laid_out(seen, initial), A.MODEL, known, table)
    assert np.allclose(net.params["next"], A.log_after(A.after_rows(net, every)))
    company = A.company_of(train, seen, A.MODEL, known, table)
    order = np.lexsort((np.arange(size), -seen))[: A.TOLD]
    told = np.array([np.isin(order, x[1:-1]).astype(float) for x in every]).sum(0)
    assert ((company.sum(1) > 0) == (told > 0)).all() and company.sum() > 0.9 * sum(len(x) - 2 for x in every)


def test_turns_add_up():
    r = np.random.default_rng(4)
    texts = [np.concatenate([[A.START], r.integers(3, 40, 50), [A.END]]).astype(np.int32) for _ in range(12)]
    net = A.laid_out(np.bincount(np.concatenate(texts), minlength=50), np.arange(50) % 2 == 0)
    training = A.Training(net)
    for at in range(0, 12, 5):
        training.turn(texts[at : at + 5])
    assert (training.pairs == A.after_rows(net, texts)).all() and training.weight == sum(map(len, texts))
    assert not net.params["next"].any()  # the net given is left as it was
