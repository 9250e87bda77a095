"""Multilevel partitioning: matching, contraction, initial partitions, projection and refinement.

Two forms: DataFrame steps for graphs of any size (``match``, ``contract``, ``project``), and the same
scheme in arrays for graphs under the edge limit, which the evolutionary search calls many times.
"""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.graphs import symmetric
from ..schema import Graph
from ..sources.scratch import settled
from .local import Local

#: Nodes that are looked at together for a move.
AT_ONCE = 512

# --- DataFrame steps


def match(g: Graph, rounds: int = 3, key: DataFrame | None = None) -> DataFrame:
    """(v, cv): mutual heaviest neighbours share the smaller id; others keep theirs.

    Ties go by a hash of the unordered pair, so both ends agree. ``key`` (v, key) forbids pairs with
    different keys, as when two parents' cuts must survive.
    """
    edges = g.edges
    if key is not None:
        a, b = key.select(F.col("v").alias("u"), F.col("key").alias("ku")), key.select("v", F.col("key").alias("kv"))
        edges = edges.join(a, "u").join(b, "v").where("ku = kv").select("u", "v", "w")
    done = None
    for _ in range(rounds):
        sym = symmetric(edges)
        rank = F.struct("w", F.xxhash64(F.least("v", "nbr"), F.greatest("v", "nbr")), F.col("nbr"))
        best = sym.groupBy("v").agg(F.max_by("nbr", rank).alias("nbr"))
        pairs = best.join(best.select(F.col("nbr").alias("v"), F.col("v").alias("nbr")), ["v", "nbr"]).where("v < nbr")
        pairs = settled(pairs.select(F.col("v").alias("a"), F.col("nbr").alias("b")), "pairs")
        done = pairs if done is None else done.unionByName(pairs)
        used = pairs.select(F.explode(F.array("a", "b")).alias("x"))
        edges = edges.join(used.select(F.col("x").alias("u")), "u", "left_anti").join(used.select(F.col("x").alias("v")), "v", "left_anti").select("u", "v", "w")
    partner = done.select(F.col("b").alias("v"), F.col("a").alias("cv"))
    return g.nodes.select("v").join(partner, "v", "left").select("v", F.coalesce("cv", "v").alias("cv"))


def contract(g: Graph, mapping: DataFrame) -> Graph:
    """The graph of matched nodes: weights of nodes and of parallel edges are added, inner edges go."""
    ends = g.edges.join(mapping.select(F.col("v").alias("u"), F.col("cv").alias("cu")), "u").join(mapping, "v")
    edges = ends.where("cu <> cv").groupBy(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))
    nodes = g.nodes.join(mapping, "v").groupBy(F.col("cv").alias("v")).agg(F.sum("c").alias("c"))
    return Graph(settled(edges, "coarse-edges"), settled(nodes, "coarse-nodes"), g.name)


def project(p: DataFrame, mapping: DataFrame) -> DataFrame:
    return mapping.join(p.withColumnRenamed("v", "cv"), "cv").select("v", "b")


def guarded_moves(g: Graph, p: DataFrame, lmax: int, k: int, upward: bool) -> DataFrame:
    """One parallel refinement pass: positive gains in one direction of block ids, up to each target's room.

    Prefix sums over the order of gains keep the bound; one direction at a time keeps neighbours from
    swapping places at once.
    """
    from ..functions.measures import connections, gains, weighted_sizes

    best = gains(connections(g.edges, p)).where("a < b" if upward else "a > b").where("g > 0")
    best = best.withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("g"), "b"))).where("_r = 1").join(g.nodes, "v")
    room = p.sparkSession.range(k).select(F.col("id").cast("int").alias("b")).join(weighted_sizes(g, p), "b", "left").select("b", (F.lit(lmax) - F.coalesce("size", F.lit(0))).alias("room"))
    taken = F.sum("c").over(Window.partitionBy("b").orderBy(F.desc("g"), "v"))
    moves = best.withColumn("_taken", taken).join(F.broadcast(room), "b").where("_taken <= room").select("v", F.col("b").alias("new_b"))
    return p.join(moves, "v", "left").select("v", F.coalesce("new_b", "b").cast("int").alias("b"))


# --- Arrays


def _chance(rng):
    """A generator for whole arrays, drawn from ``rng``."""
    return np.random.default_rng(rng.getrandbits(64))


def _edges_of(n, u, v, w):
    a, b = np.minimum(u, v), np.maximum(u, v)
    keep = a != b
    key, at = np.unique(a[keep] * n + b[keep], return_inverse=True)
    return key // n, key % n, np.bincount(at, w[keep], len(key)).astype(np.int64)


def _matching(n, u, v, w, c, most: int, rng, key=None) -> np.ndarray:
    """Heavy edges first, in random order among equals; no pair grows over ``most``."""
    may = c[u] + c[v] <= most
    if key is not None:
        may &= key[u] == key[v]
    u, v, w = u[may], v[may], w[may]
    order = np.lexsort((_chance(rng).permutation(len(u)), -(w / (c[u] * c[v]))))
    partner, free = np.arange(n), bytearray(b"\1") * n
    first, second = [], []
    for a, b in zip(u[order].tolist(), v[order].tolist(), strict=True):
        if free[a] and free[b]:
            free[a] = free[b] = 0
            first.append(a)
            second.append(b)
    partner[second] = first
    return partner


def coarsened(n, u, v, w, c, k: int, rng, key=None, small: int | None = None):
    """Levels [(n, u, v, w, c, map to the next)], down to a small graph."""
    small = small or max(60, 12 * k)
    levels, most = [], max(2, int(1.5 * c.sum() / small))
    while n > small:
        partner = _matching(n, u, v, w, c, most, rng, key)
        ids, mapping = np.unique(partner, return_inverse=True)
        if len(ids) > 0.95 * n:
            break
        levels.append((n, u, v, w, c, mapping))
        u, v, w = _edges_of(len(ids), mapping[u], mapping[v], w)
        c = np.bincount(mapping, c, len(ids)).astype(np.int64)
        key = None if key is None else key[ids]
        n = len(ids)
    levels.append((n, u, v, w, c, None))
    return levels


def grown(n, u, v, w, c, k: int, lmax: int, rng) -> np.ndarray:
    """Greedy growing: each block takes the node with the strongest tie to it until it is full."""
    g = Local(u, v, w, np.zeros(n, np.int64), 1, int(c.sum()), c)
    part, goal = np.full(n, k - 1), c.sum() / k
    left = set(range(n))
    for b in range(k - 1):
        tie: dict[int, int] = {}
        size = 0
        while left and size < goal:
            x = max(tie, key=lambda y: (tie[y], -y)) if tie else rng.choice(sorted(left))
            if size and size + c[x] > lmax:
                break
            tie.pop(x, None)
            left.discard(x)
            part[x], size = b, size + int(c[x])
            for y, weight in g.near(x):
                if y in left:
                    tie[y] = tie.get(y, 0) + weight
        if not left:
            break
    return part


def local_moves(g: Local, rng, rounds: int = 8) -> None:
    """Moves with positive gain, or even ones into smaller blocks, within the bound; then the heaviest excess.

    Nodes are met one by one, in random order. Some at once are looked at for any move without loss, whatever the room:
    others can't move before one of their neighbours does.
    """
    chance, size, c = _chance(rng), g.size.tolist(), g.c
    for _ in range(rounds):
        moved = 0
        inside = g.conn[np.arange(g.n), g.part]
        edge = chance.permutation(np.flatnonzero((g.conn.sum(1) > inside) | g.over[g.part].astype(bool)))
        for at in range(0, len(edge), AT_ONCE):
            some = edge[at : at + AT_ONCE]
            own, row = g.part[some], g.conn[some]
            held = row[np.arange(len(some)), own]
            row[np.arange(len(some)), own] = -1
            may, near = ((row.max(1) >= held) | (g.over[own] > 0)).tolist(), set()
            for x, able in zip(some.tolist(), may, strict=True):
                if (able or x in near) and (b := _better(g.conn[x].tolist(), int(g.part[x]), size, int(c[x]), g.lmax)) >= 0:
                    a = int(g.part[x])
                    g.move(x, b)
                    size[a] -= int(c[x])
                    size[b] += int(c[x])
                    near.update(g.nbr[g.ptr[x] : g.ptr[x + 1]].tolist())
                    moved += 1
        if not moved:
            break


def _better(row: list[int], a: int, size: list[int], weight: int, lmax: int) -> int:
    """The block that a node of a with ties ``row`` should go to, or -1."""
    b, most = -1, None
    for i, tie in enumerate(row):
        if i != a and (most is None or tie > most) and size[i] + weight <= lmax:
            b, most = i, tie
    if b >= 0 and (most > row[a] or size[a] > lmax or (most == row[a] and size[b] + weight < size[a])):
        return b
    return -1


def partition(n, u, v, w, c, k: int, lmax: int, seed: int, key=None, start=None, tries: int = 4, cycle_refine=None) -> np.ndarray:
    """A partition with blocks up to about ``lmax`` by the multilevel scheme.

    ``start`` with ``key`` begins from a given partition that the contraction respects. ``cycle_refine``
    (a configuration) also runs the cycle search on every level, in node weights.
    """
    from .local import Refiner

    rng = random.Random(seed)
    levels = coarsened(n, *(np.asarray(x, np.int64) for x in (u, v, w, c)), k, rng, key)
    cn, cu, cv, cw, cc, _ = levels[-1]
    best = None
    if start is not None:
        down = np.asarray(start)
        for level in levels[:-1]:
            nxt = np.zeros(level[5].max() + 1, np.int64)
            nxt[level[5]] = down
            down = nxt
        best = Local(cu, cv, cw, down, k, lmax, cc)
        local_moves(best, rng)
    for _ in range(tries if best is None else 0):
        g = Local(cu, cv, cw, grown(cn, cu, cv, cw, cc, k, lmax, rng), k, lmax, cc)
        local_moves(g, rng)
        if best is None or (int(g.over.sum()), g.cut()) < (int(best.over.sum()), best.cut()):
            best = g
    part = best.part
    for level in reversed(levels[:-1]):
        g = Local(level[1], level[2], level[3], part[level[5]], k, lmax, level[4])
        local_moves(g, rng)
        if cycle_refine is not None and not g.over.any():
            Refiner(g, cycle_refine, seed).run()
        part = g.part
    return part
