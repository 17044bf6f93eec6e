"""Beams and prunings over all nodes of a graph: what they cost, and that the result is the same."""

import tracemalloc

import numpy as np
import pytest
from sidecar_ann.functions import graph as G


def test_prune_among_many_candidates_holds_no_square_of_them():
    """A table of 3000 x 3000 distances alone takes 72 MB."""
    x = np.random.default_rng(3).normal(size=(3000, 8))
    tracemalloc.start()
    kept = G.robust_prune(x, 7, np.arange(len(x)), 1.2, 12)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 24 << 20
    want: list[int] = []
    to = ((x - x[7]) ** 2).sum(1)
    for i in np.argsort(to, kind="stable"):
        if i != 7 and len(want) < 12 and all(1.44 * ((x[i] - x[j]) ** 2).sum() > to[i] for j in want):
            want.append(int(i))
    assert kept.tolist() == want


def test_full_beam_is_one_pass_over_what_the_entries_reach(monkeypatch):
    """No sort for each node that is expanded; nodes out of reach stay out."""
    rng = np.random.default_rng(5)
    x, q = rng.normal(size=(300, 6)), rng.normal(size=(4, 6))
    table = np.stack([(np.arange(300) + 1) % 290, rng.integers(0, 290, 300)], 1)
    sorts, sort = [0], np.lexsort

    def counted(*a, **b):
        sorts[0] += 1
        return sort(*a, **b)

    monkeypatch.setattr(np, "lexsort", counted)
    got = G.beam_search(x, table, np.array([3]), q, 300)
    assert sorts[0] <= len(q)
    for row, d, v in zip(got.ids, got.distance, q):
        true = ((x[:290] - v) ** 2).sum(1)
        assert row[:290].tolist() == np.argsort(true, kind="stable").tolist()
        assert d[:290] == pytest.approx(np.sort(true))
        assert (row[290:] == -1).all() and np.isinf(d[290:]).all()
    assert got.visited.tolist() == [290] * 4


@pytest.mark.parametrize("width", [1, 5, 40])
def test_a_narrow_beam_sorts_its_pool_once(width, monkeypatch):
    """Not once for each node that is expanded."""
    x = np.random.default_rng(6).normal(size=(400, 6))
    table, entries = G.build_graph(x, G.GraphParams(R=8, L=20))
    sorts, sort = [0], np.lexsort

    def counted(*a, **b):
        sorts[0] += 1
        return sort(*a, **b)

    monkeypatch.setattr(np, "lexsort", counted)
    got = G.beam_search(x, table, entries, x[:30] + 0.01, width)
    assert sorts[0] <= 2 < got.visited.max() + 2
    assert (np.diff(got.distance, axis=1) >= 0).all()
    assert (got.ids[:, 0] == np.arange(30)).mean() > 0.9 or width == 1
    for row, d, v in zip(got.ids, got.distance, x[:30] + 0.01):
        assert d == pytest.approx(((x[row] - v) ** 2).sum(1))


@pytest.mark.parametrize("R", [1, 2, 4])
def test_repair_brings_all_in_reach_and_loses_none(R):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(150, 4)) + np.repeat(np.arange(5), 30)[:, None] * 20
    table = (np.repeat(np.arange(5), 30) * 30)[:, None] + rng.integers(0, 30, (150, R))
    before = G.reachable(table, np.array([0]))
    G.repair(x, table, np.array([0]))
    after = G.reachable(table, np.array([0]))
    assert after[before].all() and after.sum() > before.sum()
    if R > 1:
        assert after.all()
