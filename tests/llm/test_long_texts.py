"""Anchors of texts longer than one slice."""

import numpy as np

from tuneloom.llm import winnowing


def test_anchors_over_seams(monkeypatch):
    draw = np.random.default_rng(2)
    for width, n, values in ((25, 8, 50), (20, 4, 3), (30, 8, 1)):
        units = draw.integers(0, values, 5000).astype(np.uint64)
        owner = np.repeat([0, 1, 2], [3000, 10, 1990])
        monkeypatch.setattr(winnowing, "PLACE_BITS", 24)
        want = winnowing.anchors(units, owner, n, width)
        # the order of hashes must not change with the slices: only the places' range is cut, not the hash bits
        whole = winnowing.PLACE_BITS
        inner = winnowing._anchors
        monkeypatch.setattr(winnowing, "PLACE_BITS", 8)

        def with_all_bits(*args):
            winnowing.PLACE_BITS = whole
            out = inner(*args)
            winnowing.PLACE_BITS = 8
            return out

        monkeypatch.setattr(winnowing, "_anchors", with_all_bits)
        got = winnowing.anchors(units, owner, n, width)
        monkeypatch.setattr(winnowing, "_anchors", inner)
        for a, b in zip(got, want):
            assert np.array_equal(a, b)


def test_text_over_the_place_bits():
    units = np.random.default_rng(3).integers(0, 256, (1 << 24) + 1000).astype(np.uint8)
    units[-600:] = units[:600]
    h, place, first, last = winnowing.anchors(units, np.zeros(len(units), np.int32), 8, 100)
    assert first[0] == 0 and last[-1] == len(units) - 100 and (first[1:] == last[:-1] + 1).all()
    inside = lambda lo: {(int(p) - lo, int(x)) for p, x, f, g in zip(place, h, first, last) if f >= lo and g <= lo + 500}
    assert {x for x in inside(0) if x[0] > 100} & {x for x in inside(len(units) - 600) if x[0] > 100}
