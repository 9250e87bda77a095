"""Cycle search against enumeration on small random digraphs."""

import random

import numpy as np
import pytest

from balcut.functions import cycles as C


def digraph(seed, n=6, negative=True):
    r = random.Random(seed)
    arcs = [(a, b, r.randint(-3 if negative else 0, 6)) for a in range(n) for b in range(n) if a != b and r.random() < 0.45]
    return (np.array(x, np.int64) for x in zip(*arcs, strict=True)) if arcs else (np.empty(0, np.int64),) * 3


@pytest.mark.parametrize("solver", list(C.SOLVERS))
@pytest.mark.parametrize("seed", range(60))
def test_negative_cycle_is_found_exactly_when_there_is_one(seed, solver):
    src, dst, w = digraph(seed)
    pi, cycle = C.negative_cycle(6, src, dst, w, solver)
    there = any(sum(w[i] for i in c) < 0 for c in C.simple_cycles(6, src, dst))
    assert (cycle is not None) == there
    if cycle:
        assert sum(w[i] for i in cycle) < 0
        assert all(dst[a] == src[b] for a, b in zip(cycle, cycle[1:] + cycle[:1], strict=True))
    else:
        assert (C.reduced(pi, src, dst, w) >= 0).all()


@pytest.mark.parametrize("seed", range(60))
def test_zero_cycle_by_potentials(seed):
    src, dst, w = digraph(seed + 1000)
    pi, cycle = C.negative_cycle(6, src, dst, w)
    if cycle is not None:
        return
    there = any(sum(w[i] for i in c) == 0 for c in C.simple_cycles(6, src, dst))
    found = C.zero_cycle(6, src, dst, w, pi, random.Random(seed))
    assert (found is not None) == there
    if found:
        assert sum(w[i] for i in found) == 0


def test_cycles_without_moves_are_not_taken():
    src, dst, w = np.array([1, 0]), np.array([0, 1]), np.array([0, 0])
    assert C.zero_cycle(2, src, dst, w, np.zeros(2, int), random.Random(0), lambda i: False) is None


@pytest.mark.parametrize("seed", range(30))
def test_shortest_path_matches_enumeration(seed):
    src, dst, w = digraph(seed, negative=False)
    best = {0: 0}
    for _ in range(6):
        for a, b, x in zip(src.tolist(), dst.tolist(), w.tolist(), strict=True):
            if a in best and best[a] + x < best.get(b, 99):
                best[b] = best[a] + x
    path = C.shortest_path(6, src, dst, w, 0, 5)
    assert (path is not None) == (5 in best)
    if path:
        assert sum(w[i] for i in path) == best[5]
