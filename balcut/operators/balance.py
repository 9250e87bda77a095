"""Balance steps: cheapest path through the model, chains of single moves, and repair across components."""

from __future__ import annotations

from collections import deque

import numpy as np

from ..functions import cycles as C
from .local import Local, conflict


def forest(g: Local, roots: list[int]) -> dict[int, int]:
    """Breadth-first parents over adjacent blocks from the overloaded ones, in the given order."""
    near: dict[int, list[int]] = {}
    for a, b in g.pairs():
        near.setdefault(a, []).append(b)
    parent, queue = {r: -1 for r in roots}, deque(roots)
    while queue:
        a = queue.popleft()
        for b in near.get(a, ()):
            if b not in parent:
                parent[b] = a
                queue.append(b)
    return parent


def path_to(parent: dict[int, int], b: int) -> list[tuple[int, int]]:
    out = []
    while parent[b] >= 0:
        out.append((parent[b], b))
        b = parent[b]
    return out[::-1]


def _seeded(run, parent, free) -> object | None:
    """A construction in which a path to some free block has been searched first; free blocks in random order."""
    for b in free:
        if parent.get(b, -1) >= 0 and (found := run.searches(path_to(parent, b))) is not None:
            return found
    return None


def by_path(run, parent, free) -> str | None:
    """The cheapest s-t path of the balancing model, after any negative cycles that the new models still have.

    A cycle may itself take nodes out of an overloaded block; then it was the step. With harvest a model gives more than
    one cycle: searches that none has used yet are neither adjacent to it nor share a node, so their gains still hold.
    """
    before = int(run.g.over.sum())
    while True:
        found = _seeded(run, parent, free)
        if found is None:
            return None
        model = run.build(balancing=True, found=found)
        keep, fresh = np.arange(len(model.arcs)), True
        while True:
            src, dst, w = model.arrays(keep)
            _, cycle = C.negative_cycle(model.t + 1, src, dst, w, run.cfg.solver)
            if cycle is None and not fresh:
                break
            steps = cycle if cycle is not None else C.shortest_path(model.t + 1, src, dst, w, model.s, model.t)
            if steps is None:
                return None
            arcs = [model.arcs[keep[i]] for i in steps]
            kind = conflict(arcs, run.g, run.cfg.conflict_rule)
            if kind is None and cycle is None:
                run.apply(arcs, "path")
                return "path"
            if kind is None:
                # A cycle improves; the model has then no path, and a new one is built.
                run.apply(arcs, "negative")
                if run.g.over.sum() < before:
                    return "negative"
                if not run.cfg.harvest:
                    break
                keep, fresh = model.unused(keep, {i for x in arcs for i in x.sids}), False
                continue
            run.trace.conflicts[kind] += 1
            keep = np.delete(keep, steps[run.rng.randrange(len(steps))])


def by_chain(run, parent, free) -> str | None:
    """For every forest path the best node hop by hop, counting earlier hops; the cheapest path's moves stay."""
    g, best = run.g, None
    for b in free:
        if parent.get(b, -1) < 0:
            continue
        cost, done = 0, []
        for x, y in path_to(parent, b):
            inside = (g.part == x).nonzero()[0]
            if len(inside):
                gains = g.conn[inside, y] - g.conn[inside, x]
                v = int(inside[gains.argmax()])
                cost -= int(gains.max())
                done.append((v, x, y))
                g.move(v, y)
        for v, x, _ in reversed(done):
            g.move(v, x)
        if done and len(done) == len(path_to(parent, b)) and (best is None or (cost, b) < best[:2]):
            best = cost, b, done
    if best is None:
        return None
    before = g.over.sum()
    for v, _, y in best[2]:
        g.move(v, y)
    if g.over.sum() >= before:  # node weights that don't fit
        for v, x, _ in reversed(best[2]):
            g.move(v, x)
        return None
    return "chain"


def by_repair(run) -> str | None:
    """Across components: a random node of an overloaded block goes to a block with room."""
    g = run.g
    rooms = [b for b in range(g.k) if g.cap[b] > 0]
    for a in (b for b in range(g.k) if g.over[b]):
        inside = (g.part == a).nonzero()[0].tolist()
        while inside:
            i = run.rng.randrange(len(inside))
            inside[i], inside[-1] = inside[-1], inside[i]
            v = inside.pop()
            fits = [b for b in rooms if g.c[v] <= g.cap[b]]
            if fits:
                g.move(v, fits[run.rng.randrange(len(fits))])
                return "repair"
    return None


def by_transfer(run, rest: int) -> int:
    """Bring a large overload down to ``rest``, a share at a time: nodes whose move costs the cut least go first; the number moved.

    Steps of one path each take a model of the whole graph, so their time would grow with the square of it.
    """
    g, moved = run.g, 0
    while int(g.over.sum()) > rest:
        before = moved
        for a in np.flatnonzero(g.over).tolist():
            share, inside, rooms = -(-int(g.over[a]) // 4), np.flatnonzero(g.part == a), np.flatnonzero(g.cap)
            if not len(rooms):
                break
            gains = g.conn[np.ix_(inside, rooms)] - g.conn[inside, a][:, None]
            goal = gains.argmax(axis=1)
            at = np.argsort(-gains[np.arange(len(inside)), goal], kind="stable")
            cap = g.cap
            for i in at.tolist():
                v, b = int(inside[i]), int(rooms[goal[i]])
                if share <= 0:
                    break
                if g.c[v] <= cap[b]:
                    g.move(v, b)
                    cap[b] -= g.c[v]
                    share -= int(g.c[v])
                    moved += 1
        if moved == before:
            break
    return moved


def balance_step(run) -> str:
    """Lower the overload by at least one: path, else chain, else repair."""
    from ..schema import InfeasibleBalance

    g = run.g
    roots = [b for b in range(g.k) if g.over[b]]
    free = [b for b in range(g.k) if g.cap[b] > 0]
    run.rng.shuffle(roots)
    run.rng.shuffle(free)
    parent = forest(g, roots)
    how = by_path(run, parent, free) or by_chain(run, parent, free) or by_repair(run)
    if how is None:
        raise InfeasibleBalance("no node of an overloaded block fits anywhere")
    return how
