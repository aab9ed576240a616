"""Large segments are built without searches of narrow windows, and by blocks of distances with the same links."""

import numpy as np
import pytest

from hybridrange.kernel import stack
from hybridrange.kernel.stack import Stack, far


def data(n, dims=8, seed=6):
    rng = np.random.default_rng(seed)
    vecs = rng.normal(size=(n, dims))
    vecs[n // 2 : n // 2 + 9] = vecs[:9]  # copies
    return vecs, rng.permutation(n)


def hits(held, vecs, codes, k=10):
    got = []
    for i in range(0, len(vecs), len(vecs) // 30):
        low, high = (0, len(vecs)) if i % 2 else (len(vecs) // 8, len(vecs) // 4)
        rows = np.flatnonzero((codes >= low) & (codes <= high))
        want = set(rows[np.argsort(far(vecs, rows, vecs[i]), kind="stable")][:k].tolist())
        got.append(len(want & set(held.query(vecs[i], (low, high), k, 64, complete=False).rows)) / k)
    return np.mean(got)


def test_a_large_segment_is_built_without_searches_of_narrow_windows(monkeypatch):
    vecs, codes = data(2_100)
    beams, plain = [], Stack.beam
    monkeypatch.setattr(Stack, "beam", lambda self, *a, **k: beams.append(1) or plain(self, *a, **k))
    held = Stack(vecs, codes).build()
    assert not beams and held.count == 2_100 and hits(held, vecs, codes) > 0.95
    for layer in held.links:
        assert all(len(mine) <= 16 and i not in mine and len(set(mine)) == len(mine) for i, mine in enumerate(layer))


def test_blocks_of_distances_make_the_same_links(monkeypatch):
    vecs, codes = data(400)
    for name, value in (("LARGE", 50), ("AT_ONCE", 60), ("AT_ONCE_QUERY", 60), ("BLOCK", 3_000)):
        monkeypatch.setattr(stack, name, value)
    beams, plain = [], Stack.beam
    monkeypatch.setattr(Stack, "beam", lambda self, *a, **k: beams.append(1) or plain(self, *a, **k))
    blocks = Stack(vecs, codes).build()
    assert len(beams) > 300 and blocks.ahead is None and hits(blocks, vecs, codes) > 0.95
    monkeypatch.setattr(stack, "MOST", 0)
    assert Stack(vecs, codes).build().links == blocks.links


@pytest.mark.parametrize("cap", [1, 4, 8])
def test_a_first_look_keeps_the_same_rows(monkeypatch, cap):
    vecs, _ = data(200)
    for i in range(0, 200, 10):
        d = far(vecs, slice(None), vecs[i])
        rows = [r for r in np.argsort(d, kind="stable").tolist() if r != i][:64]
        told = stack.diverse(vecs, d[rows].tolist(), rows, cap)
        with monkeypatch.context() as whole:
            whole.setattr(stack, "FIRST", 1_000)
            assert told == stack.diverse(vecs, d[rows].tolist(), rows, cap)
