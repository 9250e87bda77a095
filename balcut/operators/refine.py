"""Refinement of a partitioned graph in DataFrames: engine choice, one-task engine, and the distributed engine."""

from __future__ import annotations

import random
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import cycles as C
from ..functions import measures as M
from ..functions.graphs import symmetric
from ..functions.order import ranked
from ..schema import BalanceSpec, Graph, RefineConfig
from ..sources.scratch import settled
from .local import Arc, Local, Model, Refiner, Search, Trace, best_prefixes, conflict

#: Candidates of an ordered pair of blocks that a round looks at first; pairs that need more get twice as many, again and again.
TOP = 32
#: Rows about candidates and searches that a round may bring to the driver.
MODEL_ROWS = 2_000_000
#: Of nodes near the searches: rows that may come to the driver, nodes from which one more hop is looked ahead, and hops at once.
NEAR_ROWS, NEAR_NODES, NEAR_HOPS = 500_000, 4096, 4


@dataclass
class Refined:
    part: DataFrame
    trace: dict = field(default_factory=dict)


class TooLarge(ValueError):
    """The graph is over the limit of the one-task engine."""


def _rows(g: Graph, p: DataFrame) -> DataFrame:
    """Edges and placed nodes as rows of one table, which one task reads."""
    e = g.edges.select(F.lit(0).cast("tinyint").alias("kind"), F.col("u").alias("x"), F.col("v").alias("y"), "w")
    n = g.nodes.join(p, "v").select(F.lit(1).cast("tinyint").alias("kind"), F.col("v").alias("x"), F.col("b").cast("long").alias("y"), F.col("c").alias("w"))
    return e.unionByName(n)


def arrays_of(kind, x, y, w):
    """(node ids, u, v, w, part, weights) with nodes by place in the order of ids."""
    node = kind == 1
    order = np.argsort(x[node])
    ids, part, c = (z[node][order] for z in (x, y, w))
    u, v, weight = (z[~node] for z in (x, y, w))
    order = np.lexsort((v, u))
    return ids, np.searchsorted(ids, u[order]), np.searchsorted(ids, v[order]), weight[order], part, c


def arrays(pdf: pd.DataFrame):
    return arrays_of(*(pdf[c].to_numpy() for c in ("kind", "x", "y", "w")))


def in_one_task(g: Graph, p: DataFrame, work, limit: int) -> Refined:
    """Run ``work(ids, u, v, w, part, c) -> (part, trace)`` in one task on a graph of a checked size."""
    m = g.edges.count()
    if m > limit:
        raise TooLarge(f"{m} edges; one task takes {limit} at most")

    def run(batches):
        ids, u, v, w, part, c = arrays(pd.concat(list(batches)))
        new, trace = work(ids, u, v, w, part, c)
        yield pd.DataFrame({"v": ids, "b": np.asarray(new, np.int32), "name": None})
        yield pd.DataFrame({"v": [int(x) for x in trace.values()], "b": 0, "name": [str(k) for k in trace]})

    done = settled(_rows(g, p).coalesce(1).mapInPandas(run, "v long, b int, name string"), "refined")
    trace = {r["name"]: r["v"] for r in done.where("name is not null").collect()}
    return Refined(done.where("name is null").select("v", "b"), trace)


def flat(trace: Trace) -> dict[str, int]:
    """A trace as names and whole numbers."""
    out = dict(trace.counts)
    out |= {f"conflict {k}": n for k, n in trace.conflicts.items()} | {f"cycle {k} {n}": c for (k, n), c in trace.cycles.items()} | {f"model {k}": n for k, n in trace.model.items()}
    return out | {"millis": int(1000 * trace.secs)}


def replay(g: Graph, p: DataFrame, spec: BalanceSpec, cfg: RefineConfig, seed: int = 0) -> Refined:
    def work(ids, u, v, w, part, c):
        local = Local(u, v, w, part, spec.k, spec.lmax, c)
        before = local.cut()
        trace = Refiner(local, cfg, seed).run()
        return local.part, flat(trace) | {"cut_before": before, "cut_after": local.cut()}

    return in_one_task(g, p, work, cfg.local_edge_limit)


class Parallel:
    """Rounds over DataFrames. The graph stays distributed; only rows about candidates reach the driver.

    Of a round's searches, all pairs run at once. Where two touch, the later in a hashed order is cut to
    its prefix before the contact; a prefix stays exact, since its gains are cumulative.

    An overloaded start is first made feasible by ``repair``; nodes have unit weights here, others are refused.
    Candidates are adjacent to the other block and moved nodes are marked: options for other scopes, and for
    swaps beside the model, belong to the one-task engine and are refused too.
    """

    def __init__(self, g: Graph, p: DataFrame, spec: BalanceSpec, cfg: RefineConfig, seed: int = 0):
        if cfg.candidate_scope != "pair" or cfg.mark_scope != "moved" or cfg.swap_polish:
            raise ValueError("the distributed engine has candidate_scope='pair', mark_scope='moved' and no swap_polish")
        if g.nodes.where("c <> 1").limit(1).count():
            raise ValueError("the distributed engine takes nodes of unit weight")
        self.spec, self.cfg, self.seed = spec, cfg, seed
        self.g = Graph(settled(g.edges, "edges"), settled(g.nodes, "nodes"), g.name)
        self.part = settled(p, "part")
        self.conn = settled(M.connections(self.g.edges, self.part), "conn")
        self.cut = M.cut(self.g.edges, self.part)
        self.sizes = {r["b"]: r["size"] for r in M.blocks(self.g, self.part, spec).collect()}
        self.trace: dict[str, int] = defaultdict(int)
        self.rng = random.Random(seed)

    def repair(self) -> int:
        """Bring every block under its bound; the number of moved nodes.

        What each overloaded block has too much goes to blocks with room, adjacent ones first, by the nodes whose
        move costs the cut least. All nodes of a transfer are told by rank, without a sort of the whole block, and
        connections are made anew after it. Blocks without common edges, empty ones too, take part, so this never fails.
        """
        near = {(r["a"], r["b"]): r["w"] for r in M.quotient(self.g.edges, self.part).collect()}
        lmax, moved = self.spec.lmax, 0
        over = {b: n - lmax for b, n in self.sizes.items() if n > lmax}
        room = {b: lmax - self.sizes.get(b, 0) for b in range(self.spec.k) if self.sizes.get(b, 0) < lmax}
        pairs = sorted(((a, b) for a in over for b in room), key=lambda x: (-near.get((min(x), max(x)), 0), x))
        for a, b in pairs:
            n = min(over[a], room[b])
            if not n:
                continue
            toward = self.conn.where(F.col("own") == a).groupBy("v").agg(F.sum(F.when(F.col("b") == b, F.col("w")).when(F.col("b") == a, -F.col("w")).otherwise(0)).alias("g"))
            cost = self.part.where(F.col("b") == a).join(toward, "v", "left").select("v", (-F.coalesce("g", F.lit(0))).alias("cost"))
            chosen = ranked(cost, F.col("cost"), "v").where(F.col("i") < n).select("v", F.lit(b).alias("_to"))
            self.part = settled(self.part.join(chosen, "v", "left").select("v", F.coalesce("_to", "b").cast("int").alias("b")), "part")
            self.conn = settled(M.connections(self.g.edges, self.part), "conn")
            over[a] -= n
            room[b] -= n
            self.sizes[a] -= n
            self.sizes[b] = self.sizes.get(b, 0) + n
            moved += n
        self.cut = M.cut(self.g.edges, self.part)
        return moved

    def ranks(self, blocked: DataFrame | None, salt: int) -> DataFrame:
        """The eligible nodes of every ordered pair by gain; ties by a hash that changes with each round."""
        gain = M.gains(self.conn)
        if blocked is not None:
            gain = gain.join(blocked, "v", "left_anti")
        order = (F.desc("g"), F.col("v") if self.cfg.tie == "lex" else F.xxhash64("v", F.lit(salt)), F.col("v"))
        return gain.withColumn("rank", F.row_number().over(Window.partitionBy("a", "b").orderBy(*order)))

    def seeds(self, gain: DataFrame, blocked: DataFrame | None, salt: int) -> DataFrame:
        """The first of ``ranks`` for every pair, by one aggregation; ``gain`` is the gains of all nodes."""
        if blocked is not None:
            gain = gain.join(blocked, "v", "left_anti")
        tie = F.col("v") if self.cfg.tie == "lex" else F.xxhash64("v", F.lit(salt))
        first = F.min(F.struct((-F.col("g")).alias("g"), tie.alias("t"), F.col("v").alias("v")))
        return gain.groupBy("a", "b").agg(first.alias("s")).select(F.col("s.v").alias("v"), "a", "b", (-F.col("s.g")).alias("g"), F.lit(1).alias("rank"))

    def basic_searches(self, salt: int, top: int = TOP) -> list[Search]:
        """One independent node for each pair: candidates and the edges among them decide on the driver.

        A pair whose candidates are all blocked, though it has more, gets twice as many until it finds one or has
        shown all; the choice is then the one that whole lists would give.
        """
        held = settled(self.ranks(None, salt).where(F.col("rank") <= top), "seeds")
        lists: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
        for r in self._bounded(held).orderBy("a", "b", "rank").collect():
            lists[r["a"], r["b"]].append((r["v"], r["g"]))
        pairs = sorted(lists)
        if self.cfg.order != "lex":
            self.rng.shuffle(pairs)
        limit = dict.fromkeys(pairs, top)
        while True:
            ids = F.broadcast(held.select("v").distinct())
            among = self.g.edges.join(ids, "v", "left_semi").join(ids.select(F.col("v").alias("u")), "u", "left_semi")
            near = defaultdict(set)
            for r in among.select("u", "v").collect():
                near[r["u"]].add(r["v"])
                near[r["v"]].add(r["u"])
            blocked, found, starved = set(), [], []
            for a, b in pairs:
                pick = next(((v, x) for v, x in lists[a, b] if v not in blocked), None)
                if pick:
                    blocked |= {pick[0]} | near[pick[0]]
                    found.append(Search(len(found), a, b, 0, [pick[0]], [pick[1]], [1]))
                elif len(lists[a, b]) == limit[a, b]:
                    starved.append((a, b))
                    break  # later picks depend on this one
            if not starved:
                return found
            (a, b) = starved[0]
            more = settled(self.ranks(None, salt).where((F.col("a") == a) & (F.col("b") == b) & (F.col("rank") > limit[a, b]) & (F.col("rank") <= 2 * limit[a, b])), "seeds")
            lists[a, b] += [(r["v"], r["g"]) for r in self._bounded(more).orderBy("rank").collect()]
            limit[a, b] *= 2
            held = held.unionByName(more)
            self.trace["refills"] += 1

    def _bounded(self, df: DataFrame) -> DataFrame:
        n = df.count()
        if n > MODEL_ROWS:
            raise TooLarge(f"{n} rows about one model; fewer blocks or candidates are needed")
        return df

    def bands(self, seeds: DataFrame, blocked: DataFrame | None, tau: int) -> DataFrame:
        """(a, b, v, g, nbr, w): eligible nodes of block a that a search of ``tau`` steps from the best seed can reach, with gains and ties among them."""
        sym = symmetric(self.g.edges)
        own = self.part.select("v", F.col("b").alias("a"))
        front = band = seeds.where("rank = 1").select("a", "b", "v")
        for _ in range(tau - 1):
            front = front.join(sym, "v").select("a", "b", F.col("nbr").alias("v")).join(own, ["v", "a"], "left_semi").distinct()
            if blocked is not None:
                front = front.join(blocked, "v", "left_anti")
            front = settled(front.join(band, ["a", "b", "v"], "left_anti").select("a", "b", "v"), "front")
            if front.limit(1).count() == 0:
                break
            band = band.unionByName(front)
        band = settled(band, "band")
        inside = self.conn.where("b = own").select("v", F.col("w").alias("inner"))
        toward = self.conn.select("v", "b", F.col("w").alias("outer"))
        base = band.join(inside, "v", "left").join(toward, ["v", "b"], "left")
        base = base.select("a", "b", "v", (F.coalesce("outer", F.lit(0)) - F.coalesce("inner", F.lit(0))).alias("g"))
        ties = band.join(sym, "v").join(band.select("a", "b", F.col("v").alias("nbr")), ["a", "b", "nbr"], "left_semi").select("a", "b", "v", "nbr", "w")
        return base.join(ties, ["a", "b", "v"], "left")

    def _some(self, nodes: set[int]) -> DataFrame:
        return F.broadcast(self.part.sparkSession.createDataFrame(pd.DataFrame({"v": np.fromiter(nodes, np.int64, len(nodes))}), "v long"))

    def followed(self, seeds: DataFrame, blocked: DataFrame | None, tau: int, base_sid: int) -> list[tuple] | None:
        """The rows of ``speculated``, found by looking up only nodes near the searches; None where these are too many for the driver.

        A step needs the neighbours of the node that moves, and their gains. Searches go on until one needs a node that
        isn't known; then what lies a few hops around all such nodes is looked up at once.
        """
        sym, k = symmetric(self.g.edges), self.spec.k
        near: dict[int, list[tuple[int, int]]] = {}
        toward: dict[int, dict[int, int]] = {}
        own: dict[int, int] = {}
        shut: set[int] = set()
        rows = 0

        def few(df: DataFrame) -> list | None:
            nonlocal rows
            found = settled(df, "near")
            rows += found.count()
            return found.collect() if rows <= NEAR_ROWS else None

        def look(front: set[int]) -> bool:
            """Learn the neighbours of ``front``, of some hops more where they are few, and all their connections."""
            for _ in range(NEAR_HOPS):
                found = few(sym.join(self._some(front), "v").select("v", "nbr", "w"))
                if found is None:
                    return False
                near.update((v, []) for v in front)
                for v, y, w in found:
                    near[v].append((y, w))
                front = {y for v in front for y, _ in near[v]} - near.keys()
                if not front or len(front) > NEAR_NODES:
                    break
            new = {y for some in near.values() for y, _ in some} - own.keys()
            if new:
                ids = self._some(new)
                found = few(self.conn.join(ids, "v").select("v", "own", "b", "w"))
                closed = few(blocked.join(ids, "v").select("v")) if blocked is not None else []
                if found is None or closed is None:
                    return False
                for v, a, b, w in found:
                    own[v] = a
                    toward.setdefault(v, {})[b] = w
                shut.update(r["v"] for r in closed)
            return True

        out: list[tuple] = []
        waiting = [(r["a"], r["b"], {r["v"]: r["g"]}, {r["v"]}, [], 0) for r in seeds.orderBy("a", "b").collect()]
        while waiting:
            stopped = []
            for a, b, gain, live, moved, total in waiting:
                while live and len(moved) < tau:
                    x = max(live, key=lambda y: (gain[y], -y))  # noqa: B023
                    if x not in near:
                        stopped.append((a, b, gain, live, moved, total))
                        break
                    live.discard(x)
                    moved.append(x)
                    total += gain[x]
                    out.append((a * k + b + base_sid, a, b, len(moved), x, total))
                    for y, w in near[x]:
                        if own[y] == a and y not in shut and y not in moved:
                            gain[y] = gain.get(y, toward[y].get(b, 0) - toward[y].get(a, 0)) + 2 * w
                            live.add(y)
            waiting = stopped
            if waiting and not look({max(live, key=lambda y: (gain[y], -y)) for _, _, gain, live, _, _ in waiting}):  # noqa: B023
                return None
        return out

    def speculated(self, seeds: DataFrame, blocked: DataFrame | None, tau: int, base_sid: int) -> DataFrame:
        """(sid, a, b, d, v, g): a search of ``tau`` steps from the best seed of each pair, as if there were no others.

        Searches are followed node by node; where too many rows lie near them, whole bands go to tasks instead.
        """
        rows = self.followed(seeds, blocked, tau, base_sid)
        if rows is not None:
            return self.part.sparkSession.createDataFrame(rows, "sid long, a int, b int, d int, v long, g long")
        return self.banded(seeds, blocked, tau, base_sid)

    def banded(self, seeds: DataFrame, blocked: DataFrame | None, tau: int, base_sid: int) -> DataFrame:
        """The rows of ``speculated`` from bands that hold all a search can reach."""
        k = self.spec.k

        def search(pdf):
            a, b = int(pdf.a.iloc[0]), int(pdf.b.iloc[0])
            base = pdf.drop_duplicates("v").sort_values("v")
            gain = dict(zip(base.v.tolist(), base.g.tolist(), strict=True))
            near = defaultdict(list)
            for x, y, w in pdf.loc[pdf.nbr.notna(), ["v", "nbr", "w"]].itertuples(index=False):
                near[int(x)].append((int(y), int(w)))
            live, out, total, moved = {int(pdf.loc[pdf["seed"], "v"].iloc[0])}, [], 0, set()
            while live and len(out) < tau:
                x = max(live, key=lambda y: (gain[y], -y))
                live.discard(x)
                moved.add(x)
                total += gain[x]
                out.append((a * k + b + base_sid, a, b, len(out) + 1, x, total))
                for y, w in near[x]:
                    if y not in moved:
                        gain[y] += 2 * w
                        live.add(y)
            return pd.DataFrame(out, columns=["sid", "a", "b", "d", "v", "g"])

        band = self.bands(seeds, blocked, tau).join(F.broadcast(seeds.where("rank = 1").select("a", "b", F.col("v").alias("_s"))), ["a", "b"]).withColumn("seed", F.col("v") == F.col("_s")).drop("_s")
        return settled(band.groupBy("a", "b").applyInPandas(search, "sid long, a int, b int, d int, v long, g long"), "searches")

    def layered_searches(self, salt: int, tau: int, mu: int) -> list[Search]:
        """``mu`` times: speculate on all pairs at once, then reconcile, then block what was moved and its neighbours."""
        blocked, kept = None, None
        k = self.spec.k
        gain = settled(M.gains(self.conn), "gains")
        for it in range(mu):
            seeds = settled(self.seeds(gain, blocked, salt + it), "seeds")
            if seeds.limit(1).count() == 0:
                break
            found = self.speculated(seeds, blocked, tau, it * k * k)
            found = settled(reconciled(found, self.g.edges, salt), "searches")
            kept = found if kept is None else kept.unionByName(found)
            moved = found.select("v").distinct()
            near = self.g.edges.join(F.broadcast(moved), "v").select(F.col("u").alias("v")).unionByName(self.g.edges.join(F.broadcast(moved.withColumnRenamed("v", "u")), "u").select("v"))
            now = moved.unionByName(near).distinct()
            if it + 1 < mu:
                blocked = settled(now if blocked is None else blocked.unionByName(now).distinct(), "blocked")
        out: dict[int, Search] = {}
        for r in self._bounded(kept).orderBy("sid", "d").collect() if kept is not None else ():
            s = out.setdefault(r["sid"], Search(r["sid"], r["a"], r["b"], r["sid"] // (k * k), [], [], []))
            s.nodes.append(r["v"])
            s.gains.append(r["g"])
            s.weights.append(r["d"])
        return list(out.values())

    def model(self, searches: list[Search]) -> Model:
        view = Blocks(self.spec, self.sizes)
        return Model(view, best_prefixes(searches, self.cfg.combine), self.cfg)

    def apply(self, arcs: list[Arc], weight: int) -> None:
        rows = [(v, x.a, x.b) for x in arcs for v in x.moves]
        moves = self.part.sparkSession.createDataFrame(rows, "v long, old_b int, new_b int")
        self.part = settled(M.apply_moves(self.part, moves), "part")
        # Only moved nodes and their neighbours change; the others' connections are copied without a shuffle.
        near = symmetric(self.g.edges).join(F.broadcast(moves.select(F.col("v").alias("nbr"))), "nbr").select("v")
        touched = settled(moves.select("v").unionByName(near).distinct(), "touched")
        again = M.apply_delta(self.conn.join(F.broadcast(touched), "v", "left_semi"), self.g.edges, moves)
        self.conn = settled(self.conn.join(F.broadcast(touched), "v", "left_anti").unionByName(again), "conn")
        for _, a, b in rows:
            self.sizes[a] -= 1
            self.sizes[b] = self.sizes.get(b, 0) + 1
        self.cut += weight

    def round(self, salt: int) -> int:
        """One model and its negative cycles on disjoint blocks, else a zero cycle; the gain."""
        tau = self.cfg.steps(self.spec.k)
        searches = self.basic_searches(salt) if self.cfg.model == "basic" else self.layered_searches(salt, tau, self.cfg.mu)
        model = self.model(searches)
        self.trace["models"] += 1
        keep, chosen = list(range(len(model.arcs))), []
        while keep:
            src, dst, w = model.arrays(keep)
            pi, cycle = C.negative_cycle(model.t + 1, src, dst, w, self.cfg.solver)
            if cycle is None and not chosen and self.cfg.zero_cycles and len(keep) == len(model.arcs):
                cycle = C.zero_cycle(model.t + 1, src, dst, w, pi, self.rng, lambda i: bool(model.arcs[keep[i]].moves))  # noqa: B023
            if cycle is None:
                break
            arcs = [model.arcs[keep[i]] for i in cycle]
            kind = conflict(arcs, Blocks(self.spec, self.sizes), self.cfg.conflict_rule)
            if kind:
                self.trace[f"conflict {kind}"] += 1
                drop = keep[cycle[self.rng.randrange(len(cycle))]]
                keep = [i for i in keep if i != drop]
                continue
            self.trace["cycles"] += 1
            self.trace[f"cycle any {sum(bool(x.moves) for x in arcs)}"] += 1
            chosen += arcs
            if not self.cfg.harvest:
                break
            used = {b for x in arcs if x.moves for b in (x.a, x.b)}
            inside = lambda node: node < model.s and node // model.layers in used  # noqa: B023, E731
            keep = [i for i in keep if not inside(model.arcs[i].src) and not inside(model.arcs[i].dst)]
        if not chosen:
            return 0
        gain = -sum(x.w for x in chosen)
        self.apply(chosen, -gain)
        return gain

    def run(self, max_rounds: int | None = None) -> Refined:
        before, fails = self.cut, 0
        if max(self.sizes.values(), default=0) > self.spec.lmax:
            self.trace["repaired"] = self.repair()
        for r in range(max_rounds or self.cfg.max_rounds):
            gain = self.round(self.seed * 1009 + r)
            self.trace["rounds"] = r + 1
            fails = 0 if gain else fails + 1
            if fails >= self.cfg.lam:
                break
        true = M.cut(self.g.edges, self.part)
        if true != self.cut:
            raise AssertionError(f"tracked cut {self.cut}, true cut {true}")
        if not M.is_feasible(self.g, self.part, self.spec):
            raise AssertionError("a block is over its bound")
        return Refined(self.part, dict(self.trace) | {"cut_before": before, "cut_after": true})


class Blocks:
    """Sizes of blocks in the form that models and conflict tests read; unit node weights."""

    class _Unit:
        def __getitem__(self, x):
            return np.ones(len(x), np.int64)

    def __init__(self, spec: BalanceSpec, sizes: dict[int, int]):
        self.k, self.lmax = spec.k, spec.lmax
        self.size = np.array([sizes.get(b, 0) for b in range(spec.k)], np.int64)
        self.cap, self.over = np.maximum(self.lmax - self.size, 0), np.maximum(self.size - self.lmax, 0)
        self.c = self._Unit()


def reconciled(searches: DataFrame, edges: DataFrame, salt: int = 0) -> DataFrame:
    """Searches cut to prefixes of which no two are adjacent or share a node; of two, the one first in a hashed order stays."""
    m = searches.select("sid", "d", "v", F.xxhash64("sid", F.lit(salt)).alias("prio"))
    small = F.broadcast(m)
    other = m.select(F.col("sid").alias("s2"), F.col("d").alias("d2"), F.col("v").alias("v2"), F.col("prio").alias("p2"))
    touch = symmetric(edges).join(small, "v").select("sid", "d", "prio", F.col("nbr").alias("v2")).unionByName(m.select("sid", "d", "prio", F.col("v").alias("v2")))
    met = touch.join(F.broadcast(other), "v2").where("sid <> s2 and (prio > p2 or (prio = p2 and sid > s2))")
    limit = met.groupBy("sid").agg(F.min("d").alias("_stop"))
    return searches.join(limit, "sid", "left").where("_stop is null or d < _stop").drop("_stop")


def refine(g: Graph, p: DataFrame, spec: BalanceSpec, cfg: RefineConfig, seed: int = 0) -> Refined:
    """Improve a partition. The engine is chosen by the number of edges unless the configuration names one.

    Overload is repaired by the one-task engine's balance steps or, on larger graphs, by transfers between blocks.
    """
    engine = cfg.engine or ("replay" if g.edges.limit(cfg.local_edge_limit + 1).count() <= cfg.local_edge_limit else "parallel")
    return replay(g, p, spec, cfg, seed) if engine == "replay" else Parallel(g, p, spec, cfg, seed).run()
