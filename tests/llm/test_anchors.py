"""Anchors of windows by slices against their definition, across the ends of slices."""

import numpy as np

from hcube.llm import suffix_dedup
from hcube.llm.words import STEP, U, mix


def test_slices_change_no_anchor(monkeypatch):
    rng = np.random.default_rng(4)
    lengths = [50, 51, 120, 700, 333]
    buf, stops = rng.integers(97, 101, sum(lengths)).astype(np.uint8), np.cumsum(lengths)
    monkeypatch.setattr(suffix_dedup, "SLICE", 1 << 20)
    whole, _ = suffix_dedup.window_minima(buf, stops)
    want, least = set(), np.zeros(len(buf), U)
    for a, z in zip([0, *stops[:-1]], stops):
        for s in range(a, z - suffix_dedup.LENGTH + 1):
            window = whole[s : s + suffix_dedup.REACH + 1]
            least[s] = window.min()
            want |= set((s + np.flatnonzero(window == window.min())).tolist())
    for size in (1 << 20, 64, 101):
        monkeypatch.setattr(suffix_dedup, "SLICE", size)
        h, m = suffix_dedup.window_minima(buf, stops)
        assert (m == least).all() and set(suffix_dedup.anchors(h, m).tolist()) == want


def test_numbers_are_mixed_alike_by_slices():
    x = np.random.default_rng(5).integers(0, 2**63, 2 * STEP + 5).astype(U)
    assert (mix(x)[STEP - 2 : STEP + 2] == mix(x[STEP - 2 : STEP + 2])).all() and len(mix(x[:0])) == 0
