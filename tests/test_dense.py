"""Bounded memory on dense lines."""

from __future__ import annotations

import tracemalloc

import numpy as np

from fixgap.operators import kernel
from fixgap.params import Params


def test_dense_lines_take_bounded_memory():
    """Fifty types at nearly every tick: an event has some 240 followers, which used to be held all at once."""
    at = np.argwhere(np.random.default_rng(2).random((50, 3000)) < 0.95)
    tracemalloc.start()
    picks, _, _ = kernel.select(at[:, 1] + 1, at[:, 0] + 1, Params(max_rounds=1))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert picks and peak < 200 << 20, peak


def test_products_count_as_followers_do():
    rng = np.random.default_rng(5)
    for share in (0.05, 0.3, 0.9):
        at = np.argwhere(rng.random((7, 500)) < share)
        ev = kernel.Events(at[:, 1] + 1, at[:, 0] + 1)
        paths = {int(e): ((int(e),), (), 1) for e in np.unique(ev.e)}
        row, i, gap = kernel.followers(ev, ev.t, 5)
        ok = ev.e[row] != ev.e[i]
        kinds, n = np.unique(np.stack([ev.e[row], ev.e[i], gap])[:, ok], axis=1, return_counts=True)
        got = kernel._extensions_by_product(ev, ev.e, ev.t, paths, 5, block=64)
        assert sorted(zip(*map(np.ndarray.tolist, got), strict=True)) == sorted(zip(*kinds.tolist(), n.tolist(), strict=True))
        cands = [c for c in kernel.best_paths(ev, Params()) if c.value > 0]
        assert not cands or kernel._by_rows(ev, cands, block=64) == kernel.overlaps(ev, cands)
