"""Sweeps that share work between settings give what each setting gives alone."""

import numpy as np
import pytest

from fixgap import api
from fixgap.operators import kernel
from fixgap.params import Params
from fixgap.plans import workloads


def test_sweep_selects_once_for_each_gap(spark, small, monkeypatch):
    ev = workloads.conveyor_events(spark, small, "two")[0]
    want = []
    for k in (1, 5, 20, None):
        r = api.select(ev, params=Params(k=k)).lengths().first()
        want.append((k, r["total_units"], r["n_patterns"], r["ratio"]))
    calls, select = [], workloads.select
    monkeypatch.setattr(workloads, "select", lambda *a, **k: calls.append(1) or select(*a, **k))
    got = [tuple(r)[1:] for r in workloads.sweep(spark, small).where("parameter = 'k'").collect()]
    assert got == want and len(calls) == 4


@pytest.mark.parametrize("selector,p", [("path_greedy", Params()), ("two_phase", Params(fth=0.02, max_size=3))])
def test_ignored_overlaps_are_not_counted(monkeypatch, selector, p):
    rng = np.random.default_rng(3)
    t, e = rng.integers(0, 2000, 900), rng.integers(1, 6, 900)
    found = kernel.select(t, e, p.but(max_rounds=1), selector)[2][0][1:3]

    def fail(*_):
        raise AssertionError("overlaps were counted")

    monkeypatch.setattr(kernel, "overlaps", fail)
    assert kernel.select(t, e, p.but(max_rounds=1, k=1, overlap_mode="ignore"), selector)[2][0][1:3] == found and found[1] > 0
