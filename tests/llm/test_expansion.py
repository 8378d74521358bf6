"""The transform of op10_substring_dedup: bounded common prefixes, at a cost of runs."""

import numpy as np
import pytest

from ringview.llm import substring_dedup


def _texts():
    rng = np.random.default_rng(5)
    mark = [255]
    base = rng.integers(97, 123, 120)
    near = []
    for i in range(12):
        c = base.copy()
        c[7 * i] = 65
        near += [c, mark]
    yield np.concatenate(near)
    yield np.concatenate((rng.integers(97, 99, 300), mark, rng.integers(97, 99, 200), mark))
    yield np.concatenate((np.full(150, 97), mark, np.full(90, 97), mark))
    yield np.concatenate((rng.integers(0, 255, 400), mark))
    yield np.array([97, 255])


@pytest.mark.parametrize("threes", [1 << 21, 1], ids=["threes", "twos"])
def test_bounded_prefixes_from_any_length(threes, monkeypatch):
    monkeypatch.setattr(substring_dedup, "THREES", threes)
    for text in _texts():
        text = text.astype(np.uint8)
        turned = [np.roll(text, -i)[:128].tobytes() for i in range(len(text))]
        for least in (1, 7, 8, 9, 10, 25, 60):
            order, short = substring_dedup.bounded_expansion(text, least)
            assert sorted(order.tolist()) == list(range(len(text)))
            cut = [turned[i][:least] for i in order]
            assert cut == sorted(cut)
            assert [bool(x) for x in short[1:-1]] == [a != b for a, b in zip(cut, cut[1:])], (len(text), least)


class Counted:
    """numpy, counting what is sorted."""

    def __init__(self):
        self.sorted = 0

    def __getattr__(self, name):
        if name == "argsort":
            return self._argsort
        return getattr(np, name)

    def _argsort(self, x, **how):
        self.sorted += len(x)
        return np.argsort(x, **how)


def test_near_copies_cost_their_runs(monkeypatch):
    """Each of six texts in 90 near copies: an interval of copies that go on alike is one run, however many they are."""
    rng, parts = np.random.default_rng(7), []
    for _ in range(6):
        base = rng.integers(97, 123, 900).astype(np.uint8)
        for _ in range(90):
            c = base.copy()
            c[rng.integers(900)] = 65
            parts += [c, np.array([255], np.uint8)]
    text, counted = np.concatenate(parts), Counted()
    monkeypatch.setattr(substring_dedup, "np", counted)
    order, _ = substring_dedup.bounded_expansion(text, 400)
    assert len(order) == len(text) and counted.sorted < 8 * len(text)
