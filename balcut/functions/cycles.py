"""Cycles and paths of small signed digraphs: detection, potentials, components, walks.

Arcs are (src, dst, w) in three equal arrays. These run in one place: a model's size depends on the
number of blocks and layers only, never on the graph.
"""

from __future__ import annotations

from collections import defaultdict, deque

import numpy as np


def _close(parent_arc: np.ndarray, src: np.ndarray, start: int) -> list[int] | None:
    """The cycle of parent arcs that ``start`` leads to, if there is one."""
    seen, at = set(), start
    while at not in seen:
        seen.add(at)
        if parent_arc[at] < 0:
            return None
        at = int(src[parent_arc[at]])
    cycle, x = [], at
    while True:
        cycle.append(int(parent_arc[x]))
        x = int(src[parent_arc[x]])
        if x == at:
            return cycle[::-1]


def relax_rounds(n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, list[int] | None]:
    """Rounds over all arcs at once from an all-zero start: (potentials, negative cycle or None)."""
    pi, parent = np.zeros(n, np.int64), np.full(n, -1, np.int64)
    if not len(src):
        return pi, None
    order = np.lexsort((np.arange(len(dst)), dst))
    s, d, ww = src[order], dst[order], w[order]
    first = np.flatnonzero(np.r_[True, d[1:] != d[:-1]])
    heads = d[first]
    for k in range(n + 1):
        reach = pi[s] + ww
        low = np.minimum.reduceat(reach, first)
        better = low < pi[heads]
        if not better.any():
            return pi, None
        spread = np.repeat(low, np.diff(np.r_[first, len(d)]))
        hit = np.flatnonzero(reach == spread)
        arc_of = np.full(n, -1, np.int64)
        arc_of[d[hit[::-1]]] = order[hit[::-1]]
        nodes = heads[better]
        pi[nodes], parent[nodes] = low[better], arc_of[nodes]
        if k % 4 == 3 or k == n:
            for x in nodes[:8]:
                if (cycle := _close(parent, src, int(x))) is not None:
                    return pi, cycle
    for x in range(n):
        if (cycle := _close(parent, src, x)) is not None:
            return pi, cycle
    return pi, None


def subtree_search(n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, list[int] | None]:
    """Label correcting with subtree disassembly.

    A node whose label falls takes its subtree of the shortest-path tree apart, since those labels are
    out of date; meeting the arc's own tail there closes a negative cycle. Dropped nodes leave the queue.
    """
    out: dict[int, list[int]] = defaultdict(list)
    ss, dd, ww = src.tolist(), dst.tolist(), w.tolist()
    for i, x in enumerate(ss):
        out[x].append(i)
    pi, parent, children = [0] * n, [-1] * n, [set() for _ in range(n)]
    queue, waiting = deque(range(n)), [True] * n
    while queue:
        x = queue.popleft()
        if not waiting[x]:
            continue
        waiting[x] = False
        for i in out[x]:
            y = dd[i]
            if pi[x] + ww[i] >= pi[y]:
                continue
            stack, below = [y], []
            while stack:
                z = stack.pop()
                below.append(z)
                if z == x:
                    cycle, at = [i], x
                    while at != y:
                        cycle.append(parent[at])
                        at = ss[parent[at]]
                    return np.array(pi, np.int64), cycle[::-1]
                stack += children[z]
            for z in below:
                if parent[z] >= 0:
                    children[ss[parent[z]]].discard(z)
                if z != y:  # its label falls again once y's arcs are looked at
                    parent[z], waiting[z] = -1, False
                children[z].clear()
            pi[y], parent[y] = pi[x] + ww[i], i
            children[x].add(y)
            if not waiting[y]:
                waiting[y] = True
            queue.append(y)
    return np.array(pi, np.int64), None


SOLVERS = {"plain": relax_rounds, "subtree": subtree_search}


def negative_cycle(n, src, dst, w, solver: str = "subtree"):
    """(potentials, arcs of a negative cycle in order, or None)."""
    src, dst, w = (np.asarray(x, np.int64) for x in (src, dst, w))
    if solver == "subtree" and len(src) > 20_000:
        solver = "plain"  # whole rounds in arrays beat single arcs on large models
    return SOLVERS[solver](n, src, dst, w)


def reduced(pi, src, dst, w) -> np.ndarray:
    """Arc weights under potentials: not negative, and every cycle keeps its weight."""
    pi = np.asarray(pi)
    return np.asarray(w) + pi[np.asarray(src, int)] - pi[np.asarray(dst, int)]


def strong_components(n: int, src, dst) -> list[int]:
    """The smallest node of each node's strongly connected component."""
    out, back = defaultdict(list), defaultdict(list)
    for a, b in zip(src, dst, strict=True):
        out[int(a)].append(int(b))
        back[int(b)].append(int(a))
    seen, order = [False] * n, []
    for r in range(n):
        if seen[r]:
            continue
        seen[r] = True
        stack = [(r, iter(out[r]))]
        while stack:
            x, rest = stack[-1]
            y = next((z for z in rest if not seen[z]), None)
            if y is None:
                order.append(x)
                stack.pop()
            else:
                seen[y] = True
                stack.append((y, iter(out[y])))
    comp = [-1] * n
    for r in reversed(order):
        if comp[r] < 0:
            group, stack = [], [r]
            comp[r] = r
            while stack:
                x = stack.pop()
                group.append(x)
                for y in back[x]:
                    if comp[y] < 0:
                        comp[y] = r
                        stack.append(y)
            low = min(group)
            for x in group:
                comp[x] = low
    return comp


def zero_cycle(n, src, dst, w, pi, rng, useful=None, tries: int = 4):
    """A cycle of weight zero, by a random walk in a component of the arcs with reduced weight zero.

    ``useful`` says which arcs move something; cycles without one are not taken.
    """
    src, dst = np.asarray(src, int), np.asarray(dst, int)
    tight = np.flatnonzero(reduced(pi, src, dst, w) == 0)
    if not len(tight):
        return None
    comp = strong_components(n, src[tight], dst[tight])
    inside = [i for i in tight.tolist() if comp[src[i]] == comp[dst[i]]]
    if not inside:
        return None
    out = defaultdict(list)
    for i in inside:
        out[int(src[i])].append(i)
    nodes = sorted(out)
    for _ in range(tries):
        at = nodes[rng.randrange(len(nodes))]
        when, path = {}, []
        while at not in when:
            when[at] = len(path)
            i = out[at][rng.randrange(len(out[at]))]
            path.append(i)
            at = int(dst[i])
        cycle = path[when[at] :]
        if useful is None or any(useful(i) for i in cycle):
            return cycle
    return None


def shortest_path(n, src, dst, w, s: int, t: int):
    """Arcs of a cheapest s-t path in a digraph without negative cycles, or None."""
    big = np.iinfo(np.int64).max // 4
    src, dst, w = (np.asarray(x, np.int64) for x in (src, dst, w))
    pi, parent = np.full(n, big), np.full(n, -1, np.int64)
    pi[s] = 0
    for _ in range(n):
        reach = pi[src] + w
        good = np.flatnonzero((pi[src] < big) & (reach < pi[dst]))
        if not len(good):
            break
        good = good[np.lexsort((good, reach[good]))]
        heads, first = np.unique(dst[good], return_index=True)
        pi[heads], parent[heads] = reach[good[first]], good[first]
    if pi[t] >= big:
        return None
    path, at = [], t
    while at != s and len(path) <= n:
        path.append(int(parent[at]))
        at = int(src[parent[at]])
    return path[::-1] if at == s else None


def simple_cycles(n: int, src, dst, most: int = 6):
    """All simple cycles of a tiny digraph, as lists of arcs; for checks."""
    out = defaultdict(list)
    for i, a in enumerate(src):
        out[int(a)].append(i)

    def go(start, at, path, seen):
        for i in out[at]:
            y = int(dst[i])
            if y == start:
                yield path + [i]
            elif y > start and y not in seen and len(path) + 1 < most:
                yield from go(start, y, path + [i], seen | {y})

    for x in range(n):
        yield from go(x, x, [], {x})
