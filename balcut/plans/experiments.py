"""The experiments, re-expressed on the derived graphs. One Spark task runs one instance."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures, starts
from ..operators.local import Local, Refiner, whole_type
from ..operators.refine import flat, refine
from ..schema import PRESETS, BalanceSpec, Graph, RefineConfig
from ..sources import derive
from ..sources.scratch import settled

RESULT = "workload string, graph string, k int, eps double, seed int, config string, cut_before long, cut_after long, overload_before long, overload_after long, lmax long, largest long, longest_cycle int, conflicts long, cycles long, secs double, base_secs double"
RESULT_ARROW = pa.schema([(name, {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}[kind]) for name, kind in (x.split() for x in RESULT.split(", "))])
#: Edges of an instance that one task takes.
EDGE_LIMIT = 2_000_000


def start(g: Graph, kind: str, k: int, n: int, spark: SparkSession, sf: str) -> DataFrame:
    """A start partition; chains of orders are ranked by date, all other graphs by key."""
    extra: tuple = ()
    if g.name.startswith("order_chain"):
        extra = (derive.read(spark, sf, "orders").select(F.col("o_orderkey").alias("v"), "o_orderdate"), F.to_date("o_orderdate"), ("o_orderdate", "v"))
    if kind == "chunk":
        return starts.chunk(g, k, n, *extra)
    if kind == "round_robin":
        return starts.round_robin(g, k, *extra)
    if kind == "skewed":
        return starts.skewed(g, k, n)
    if kind == "random":
        return starts.random_balanced(g, k, 1)
    return starts.mod_hash(g, k)


def _packed(g: Graph) -> DataFrame:
    """(kind, x, y, w): the edges and nodes of a graph in one table."""
    e = g.edges.select(F.lit(0).cast("tinyint").alias("kind"), F.col("u").alias("x"), F.col("v").alias("y"), "w")
    n = g.nodes.select(F.lit(1).cast("tinyint").alias("kind"), F.col("v").alias("x"), F.lit(0).cast("long").alias("y"), F.col("c").alias("w"))
    return e.unionByName(n)


def worked(work: str, r, held: list[list[np.ndarray]]) -> dict:
    """Run a work on one instance, of which ``held`` are the columns in parts; these are let go before it begins."""
    columns = []
    for _ in range(4):
        columns.append(np.concatenate([some.pop(0) for some in held]))
    held.clear()
    kind, x, y, w = columns
    columns.clear()
    node = kind == 1
    order = np.argsort(x[node])
    ids, part, c = (z[node][order] for z in (x, y, w))
    edge = ~node
    del kind, node, order
    place = whole_type(len(ids))
    u = np.searchsorted(ids, x[edge]).astype(place)
    del x
    v = np.searchsorted(ids, y[edge]).astype(place)
    del y
    weight = w[edge]
    del w, edge
    if whole_type(int(weight.max(initial=0))) is np.int32:
        weight = weight.astype(np.int32)
    order = np.lexsort((v, u))
    given = [ids, u[order], v[order], weight[order], part, c]
    del ids, u, v, weight, part, c, order
    return WORK[work](r, *given)


def spread_out(r: dict, g: Graph) -> dict:
    """``improve`` by the distributed engine, from the start that a task would make: nodes are ranked by key."""
    k, n = r["k"], g.nodes.count()
    made = {"chunk": lambda: starts.chunk(g, k, n), "skewed": lambda: starts.skewed(g, k, n), "round_robin": lambda: starts.round_robin(g, k)}
    if r["start"] not in made:
        raise ValueError(f"{r['graph']}: the distributed engine has no start {r['start']}")
    began, spec = time.time(), BalanceSpec.of(k, n, str(r["eps"]))
    p = settled(made[r["start"]](), "start")
    sizes = [x["size"] for x in measures.blocks(g, p, spec).select("size").collect()]
    done = refine(g, p, spec, config_of(r["config"]).but(engine="parallel"), r["seed"])
    after = [x["size"] for x in measures.blocks(g, done.part, spec).select("size").collect()]
    t, over = done.trace, lambda some: sum(max(0, x - spec.lmax) for x in some)
    return {
        **{x: r[x] for x in ("workload", "graph", "k", "eps", "seed", "config")}, "cut_before": t["cut_before"], "cut_after": t["cut_after"],
        "overload_before": over(sizes), "overload_after": over(after), "lmax": spec.lmax, "largest": max(after),
        "longest_cycle": max((int(x.split()[-1]) for x in t if x.startswith("cycle ")), default=0), "conflicts": sum(m for x, m in t.items() if x.startswith("conflict ")),
        "cycles": t.get("cycles", 0), "secs": time.time() - began, "base_secs": 0.0,
    }


def campaign(spark: SparkSession, sf: str, grid: list[tuple], work: str, spread: bool = False) -> DataFrame:
    """Run ``work`` on every (workload, graph, k, eps, seed, config name, start) of a grid, one task each.

    Graphs go to their tasks as whole numbers only, each copy of one under the number of its job; every task checks
    its graph's size as it reads, and holds arrays. Instances of many blocks and much room take longest and begin first. With ``spread`` graphs that no task takes go to the distributed engine.
    """
    if spread and work != "improve":
        raise ValueError("the distributed engine only improves")
    columns = ("workload", "graph", "k", "eps", "seed", "config", "start")
    jobs = {i: dict(zip(columns, x, strict=True)) for i, x in enumerate(sorted(grid, key=lambda x: (-x[2], -x[3])))}
    data, large = None, []
    for name in sorted({x[1] for x in grid}):
        g = derive.graph(spark, sf, name)
        packed = settled(_packed(g), "packed")
        if spread and packed.where("kind = 0").count() > EDGE_LIMIT:
            e, v = packed.where("kind = 0").selectExpr("x as u", "y as v", "w"), packed.where("kind = 1").selectExpr("x as v", "w as c")
            large += [spread_out(x, Graph(e, v, g.name)) for x in jobs.values() if x["graph"] == name]
            continue
        mine = F.array(*(F.lit(i) for i, x in jobs.items() if x["graph"] == name))
        rows = packed.select(F.explode(mine).alias("job"), "kind", "x", "y", "w")
        data = rows if data is None else data.unionByName(rows)

    def run(batches):
        job, held = None, []

        def out():
            r = pd.Series(jobs[job])
            row = worked(work, r, held)
            return pa.RecordBatch.from_pylist([row], schema=RESULT_ARROW)

        for batch in batches:
            at = batch.column(0).to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(at)) + 1).tolist(), len(at)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a == b:
                    continue
                if held and at[a] != job:
                    yield out()
                job = int(at[a])
                held.append([batch.column(k).slice(a, b - a).to_numpy(zero_copy_only=False).copy() for k in range(1, 5)])
                if sum(int((c[0] == 0).sum()) for c in held) > EDGE_LIMIT:
                    raise ValueError(f"{jobs[job]['graph']}: more than {EDGE_LIMIT} edges for one task")
        if held:
            yield out()

    apart = spark.createDataFrame([tuple(x[name] for name in RESULT_ARROW.names) for x in large], RESULT) if large else None
    if data is None:
        return apart
    dealt = data.repartitionById(len(jobs), F.col("job")) if len(jobs) > 1 else data.coalesce(1)
    rows = dealt.sortWithinPartitions("job").mapInArrow(run, RESULT)
    return rows if apart is None else rows.unionByName(apart)


def _start_array(kind: str, n: int, k: int):
    i = np.arange(n)
    if kind == "chunk":
        return i * k // n
    if kind == "skewed":
        return np.where(10 * i < 6 * n, 0, i % k)
    if kind == "random":
        return np.random.default_rng(1).permutation(n) % k
    return i % k


def _row(r, spec, before, g, over, trace, secs, base_secs=0.0, config=None):
    lengths = [length for (_, length) in trace.cycles] if trace else []
    return {
        "workload": r.workload, "graph": r.graph, "k": int(r.k), "eps": float(r.eps), "seed": int(r.seed), "config": config or r.config,
        "cut_before": before, "cut_after": g.cut(), "overload_before": over, "overload_after": int(g.over.sum()), "lmax": spec.lmax, "largest": int(g.size.max()),
        "longest_cycle": max(lengths, default=0), "conflicts": sum(trace.conflicts.values()) if trace else 0, "cycles": sum(trace.cycles.values()) if trace else 0,
        "secs": secs, "base_secs": base_secs,
    }


def improve(r, ids, u, v, w, part, c) -> dict:
    """Improve a given partition; starts ending in ``+swap`` are first taken to a swap optimum."""
    from ..operators.baselines import bounded_labels, swap_refine

    spec = BalanceSpec.of(int(r.k), len(ids), str(r.eps))
    kind, _, swapped = r.start.partition("+")
    g = Local(u, v, w, _start_array(kind, len(ids), spec.k), spec.k, spec.lmax, c)
    if swapped:
        swap_refine(g, 400)
    before, over, began = g.cut(), int(g.over.sum()), time.time()
    trace = None
    if r.config == "swap":
        swap_refine(g, 400)
    elif r.config == "labels":
        bounded_labels(g)
    elif r.config != "none":
        trace = Refiner(g, config_of(r.config), int(r.seed)).run()
    return _row(r, spec, before, g, over, trace, time.time() - began)


def balance_cost(r, ids, u, v, w, part, c) -> dict:
    """A multilevel partition at 1 % imbalance, then perfect balance; both cuts and both times."""
    from ..operators.multilevel import partition

    n, k = len(ids), int(r.k)
    loose, spec = BalanceSpec.of(k, n, "0.01"), BalanceSpec.of(k, n)
    began = time.time()
    got = partition(n, u, v, w, c, k, loose.lmax, int(r.seed))
    base = time.time() - began
    g = Local(u, v, w, got, k, spec.lmax, c)
    before, over, began = g.cut(), int(g.over.sum()), time.time()
    trace = Refiner(g, config_of(r.config), int(r.seed)).run()
    return _row(r, spec, before, g, over, trace, time.time() - began, base)


def scratch(r, ids, u, v, w, part, c) -> dict:
    """From scratch by the evolutionary search; the reference is the better of swaps and a multilevel run."""
    from ..operators.baselines import swap_refine
    from ..operators.evolve import Evolution
    from ..operators.multilevel import partition

    n, k = len(ids), int(r.k)
    spec = BalanceSpec.of(k, n, str(r.eps))
    one = Local(u, v, w, _start_array("chunk", n, k), k, spec.lmax, c)
    swap_refine(one, 200)
    two = Local(u, v, w, partition(n, u, v, w, c, k, spec.lmax, int(r.seed)), k, spec.lmax, c)
    Refiner(two, PRESETS["basic"].but(max_rounds=3), 1).run()
    record = one if one.cut() <= two.cut() else two
    began = time.time()
    e = Evolution(u, v, w, c, spec, config_of(r.config), int(r.seed), cycle_refine=r.config != "plain", size=4)
    best = e.run(6, seeds=[record.part] if r.start == "seeded" else [])
    g = Local(u, v, w, best.part, k, spec.lmax, c)
    return _row(r, spec, record.cut(), g, 0, None, time.time() - began)


def all_levels(r, ids, u, v, w, part, c) -> dict:
    """Refinement on every level against refinement on the last only: times as ``base_secs`` and ``secs``."""
    from ..operators.multilevel import partition

    n, k = len(ids), int(r.k)
    spec = BalanceSpec.of(k, n)
    cfg = config_of(r.config)
    began = time.time()
    a = Local(u, v, w, partition(n, u, v, w, c, k, spec.lmax, int(r.seed)), k, spec.lmax, c)
    Refiner(a, cfg, 1).run()
    last = time.time() - began
    began = time.time()
    b = Local(u, v, w, partition(n, u, v, w, c, k, spec.lmax, int(r.seed), cycle_refine=cfg.but(max_rounds=6)), k, spec.lmax, c)
    trace = Refiner(b, cfg, 1).run()
    return _row(r, spec, a.cut(), b, 0, trace, time.time() - began, last)


def config_of(name: str) -> RefineConfig:
    """A preset, optionally with changed options: ``packed:tau=7,mu=5``."""
    base, _, changes = name.partition(":")
    cfg = PRESETS.get(base, PRESETS["packed"])
    for x in filter(None, changes.split(",")):
        key, _, value = x.partition("=")
        cfg = cfg.but(**{key: value == "True" if value in ("True", "False") else int(value) if value.lstrip("-").isdigit() else value})
    return cfg


WORK = {"improve": improve, "balance_cost": balance_cost, "scratch": scratch, "all_levels": all_levels}


# --- Tables


def improved_table(results: DataFrame) -> DataFrame:
    """Share of improved instances by k and configuration, with totals."""
    better = F.avg((F.col("cut_after") < F.col("cut_before")).cast("int"))
    rows = results.select("k", "config", "cut_before", "cut_after")
    both = rows.unionByName(rows.withColumn("k", F.lit(None).cast("int")))  # the row without k holds the totals
    return both.groupBy("k").pivot("config").agg(F.round(100 * better, 1))


def vs_reference(results: DataFrame) -> DataFrame:
    """By eps and k: instances under, and not over, the reference."""
    return results.groupBy("eps").pivot("k").agg(F.count_if(F.col("cut_after") < F.col("cut_before")).alias("less"), F.count_if(F.col("cut_after") <= F.col("cut_before")).alias("not_more"))


def cost_table(results: DataFrame) -> DataFrame:
    """By k: mean increase of the cut for perfect balance, and its time relative to the multilevel run."""
    return results.groupBy("k").agg(
        F.round(100 * F.avg(F.col("cut_after") / F.greatest("cut_before", F.lit(1)) - 1), 2).alias("rel_cut"),
        F.round(100 * F.avg(F.col("secs") / F.greatest("base_secs", F.lit(1e-6))), 1).alias("rel_time"),
        F.min((F.col("overload_after") == 0).cast("int")).alias("feasible"),
    )


def feasible_rate(results: DataFrame) -> DataFrame:
    return results.groupBy("workload").agg(F.avg((F.col("largest") <= F.col("lmax")).cast("double")).alias("feasible_rate"))


__all__ = ["campaign", "improved_table", "vs_reference", "cost_table", "feasible_rate", "flat"]
