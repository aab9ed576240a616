"""The attention's arithmetic: the short way equals the careful one, and company is counted by whole slices as by texts."""

import numpy as np
import pytest

from hybridrange.llm import attention_lm as lm


def net_of(scale=1.0):
    r = np.random.default_rng(6)
    net = lm.laid_out(r.integers(0, 50, 900), r.random(900) < 0.5)
    for name, x in net.params.items():
        x += (scale * r.normal(0, 0.5, x.shape)).astype(np.float32)
    texts = [np.concatenate([[lm.START], r.integers(3, 900, n), [lm.END]]).astype(np.int32) for n in (0, 1, 19, 20, 21, 90, 333)]
    return net, texts


@pytest.mark.parametrize("scale", [1.0, 40.0])
def test_large_and_small_weights_take_the_same_steps(monkeypatch, scale):
    net, texts = net_of(scale)
    ids, then, _ = net.windows(texts)
    begins = np.arange(lm.CLASSES) % 3 == 0
    assert net.small("v", "out") == net.small("q", "k") == (scale == 1.0)
    with np.errstate(over="raise", invalid="raise"):
        g, (logs, stops) = net.gradient(ids, then), net.log_classes(ids, then, begins)
    monkeypatch.setattr(lm, "REACH", 0)
    h, (logs_, stops_) = net.gradient(ids, then), net.log_classes(ids, then, begins)
    live = then >= 0
    assert np.allclose(logs[live], logs_[live], atol=1e-4) and np.allclose(stops[live], stops_[live], atol=1e-4)
    assert g.keys() == h.keys() and all(np.allclose(g[k], h[k], atol=1e-5) for k in g)
    assert all((g[k][net.row[-1]] == 0).all() for k in "qkv")  # places outside a text learn nothing


def test_company_of_whole_slices(spark):
    r = np.random.default_rng(8)
    some = ["the", "and", "over", "river", "stone", "x" * 9, "Wide", "a"]
    texts = [" ".join(r.choice(some, n)) for n in (0, 1, 5, 40, 200)] * 70
    names = sorted({w.lower().encode() for w in some})[:5]
    known, table = {w: i for i, w in enumerate(names)}, lm.Spelled(names, lm.MODEL)
    size = lm.coder(lm.MODEL).get_piece_size()
    seen = np.bincount(table.flat, minlength=size)
    d = spark.createDataFrame([(x.encode(),) for x in texts], "text binary").repartition(3)
    got = lm.company_of(d, seen, lm.MODEL, known, table)
    order = np.lexsort((np.arange(size), -seen))[: lm.TOLD]
    rank = {int(x): i for i, x in enumerate(order)}
    want = np.zeros((lm.TOLD, lm.BY))
    for x in texts:
        told = [rank[i] for i in lm.Slice([x.encode()], lm.MODEL, known, table).texts[0][1:-1].tolist() if i in rank]
        by = np.bincount([t for t in told if t < lm.BY], minlength=lm.BY) if any(t < lm.BY for t in told) else np.zeros(lm.BY)
        for t in told:
            want[t] += by / max(1, by.sum())
    assert want.sum() > 1000 and np.allclose(got, want, rtol=1e-3)
