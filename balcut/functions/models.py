"""Models as DataFrames: candidates, prefixes, arcs, relaxations. For any number of blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import settled
from .graphs import symmetric
from .measures import connections, gains

S, T = -1, -2


def unmarked_searches(edges: DataFrame, p: DataFrame, tau: int = 2) -> DataFrame:
    """(a, b, d, v, g): every ordered pair's search without marks, ties to smaller ids.

    A step takes the best of the moved nodes' neighbours in block a; gains are cumulative.
    """
    sym = symmetric(edges)
    conn = connections(edges, p)
    inner = conn.where("b = own").select("v", F.col("w").alias("inner"))
    outer = conn.select("v", "b", F.col("w").alias("outer"))
    own = p.select("v", F.col("b").alias("a"))
    first = F.row_number().over(Window.partitionBy("a", "b").orderBy(F.desc("g"), "v"))
    step = gains(conn).withColumn("_r", first).where("_r = 1").select("a", "b", F.lit(1).alias("d"), "v", "g")
    done = last = step
    for d in range(2, tau + 1):
        near = done.select("a", "b", F.col("v").alias("m")).join(sym.withColumnRenamed("v", "m").withColumnRenamed("nbr", "v"), "m")
        near = near.join(own, ["v", "a"], "left_semi").groupBy("a", "b", "v").agg((2 * F.sum("w")).alias("bonus"))
        near = near.join(done.select("a", "b", "v"), ["a", "b", "v"], "left_anti")
        here = near.join(inner, "v", "left").join(outer, ["v", "b"], "left").withColumn("g", F.coalesce("outer", F.lit(0)) - F.coalesce("inner", F.lit(0)) + F.col("bonus"))
        best = here.withColumn("_r", first).where("_r = 1").select("a", "b", "v", "g")
        before = last.select("a", "b", F.col("g").alias("sum"))
        last = settled(best.join(before, ["a", "b"]).select("a", "b", F.lit(d).alias("d"), "v", (F.col("g") + F.col("sum")).alias("g")), "steps")
        done = done.unionByName(last)
    return done


def best_per_layer(searches: DataFrame) -> DataFrame:
    """(a, b, d, sid, g): the best of several searches of a pair for every prefix length, ties to smaller ids."""
    return searches.groupBy("a", "b", "d").agg(F.max_by(F.struct("sid", "g"), F.struct(F.col("g"), -F.col("sid"))).alias("x")).select("a", "b", "d", "x.sid", "x.g")


def _arc(df: DataFrame, src_b, src_d, dst_b, dst_d, w, kind: str) -> DataFrame:
    return df.select(*(x.cast("int").alias(n) for x, n in ((src_b, "src_b"), (src_d, "src_d"), (dst_b, "dst_b"), (dst_d, "dst_d"))), w.cast("long").alias("w"), F.lit(kind).alias("kind"))


def layer_arcs(best: DataFrame) -> DataFrame:
    return _arc(best, F.col("a"), F.col("d"), F.col("b"), F.col("d"), -F.col("g"), "move")


def up_arcs(blocks: DataFrame, layers: int) -> DataFrame:
    rows = blocks.where(F.lit(layers > 1)).select("b", F.explode(F.sequence(F.lit(1), F.lit(max(1, layers - 1)))).alias("d"))
    return _arc(rows, F.col("b"), F.col("d"), F.col("b"), F.col("d") + 1, F.lit(0), "up")


def down_arcs(best: DataFrame, blocks: DataFrame) -> DataFrame:
    """To lower layers of blocks with room; the guard keeps ``sequence`` from counting down."""
    room = best.join(F.broadcast(blocks.select("b", "cap")), "b").where("d > 1 and cap > 0")
    rows = room.select("a", "b", "d", "g", F.explode(F.sequence(F.lit(1), F.least(F.col("cap").cast("int"), F.col("d") - 1))).alias("less"))
    return _arc(rows, F.col("a"), F.col("d"), F.col("b"), F.col("d") - F.col("less"), -F.col("g"), "down")


def source_arcs(blocks: DataFrame, layers: int, only_overloaded: bool = False) -> DataFrame:
    rows = blocks.where("over > 0" if only_overloaded else "true").select("b", F.explode(F.sequence(F.lit(1), F.lit(layers))).alias("d"))
    return _arc(rows, F.lit(S), F.lit(0), F.col("b"), F.col("d"), F.lit(0), "source")


def return_arcs(blocks: DataFrame, layers: int, sink: bool = False) -> DataFrame:
    rows = blocks.where("cap > 0").select("b", F.explode(F.sequence(F.lit(1), F.least(F.col("cap").cast("int"), F.lit(layers)))).alias("d"))
    return _arc(rows, F.col("b"), F.col("d"), F.lit(T if sink else S), F.lit(0), F.lit(0), "sink" if sink else "return")


def layered_model(best: DataFrame, blocks: DataFrame, layers: int, interlayer: bool = True) -> DataFrame:
    arcs = layer_arcs(best).unionByName(source_arcs(blocks, layers)).unionByName(return_arcs(blocks, layers))
    return arcs.unionByName(up_arcs(blocks, layers)).unionByName(down_arcs(best, blocks)) if interlayer else arcs


def potentials(arcs: DataFrame, nodes: DataFrame, rounds: int) -> tuple[DataFrame, bool]:
    """(node, pi) by label correcting from an all-zero start, and whether labels still fell after ``rounds``.

    A round joins arcs with labels and keeps each node's least; ``arcs`` has (src, dst, w).
    """
    label = nodes.select("node", F.lit(0).cast("long").alias("pi"))
    for k in range(rounds + 1):
        reach = arcs.join(label.withColumnRenamed("node", "src"), "src").select(F.col("dst").alias("node"), (F.col("pi") + F.col("w")).alias("pi"))
        new = settled(label.unionByName(reach).groupBy("node").agg(F.min("pi").alias("pi")), "labels")
        fell = new.join(label.withColumnRenamed("pi", "was"), "node").where("pi < was").limit(1).count()
        label = new
        if not fell:
            return label, False
    return label, True


def distances(arcs: DataFrame, start: DataFrame, rounds: int) -> DataFrame:
    """(node, pi): cheapest ways from the start nodes with at most ``rounds`` arcs."""
    label = start.select("node", F.lit(0).cast("long").alias("pi"))
    for _ in range(rounds):
        reach = arcs.join(label.withColumnRenamed("node", "src"), "src").select(F.col("dst").alias("node"), (F.col("pi") + F.col("w")).alias("pi"))
        label = settled(label.unionByName(reach).groupBy("node").agg(F.min("pi").alias("pi")), "labels")
    return label


def reduced_arcs(arcs: DataFrame, pi: DataFrame) -> DataFrame:
    a, b = pi.select(F.col("node").alias("src"), F.col("pi").alias("pa")), pi.select(F.col("node").alias("dst"), F.col("pi").alias("pb"))
    return arcs.join(a, "src").join(b, "dst").select("src", "dst", "w", (F.col("w") + F.col("pa") - F.col("pb")).alias("l"))


def strong_components(arcs: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, comp): mutual reachability by growing the closure; for models, whose nodes are few."""
    reach = arcs.select("src", "dst").unionByName(nodes.select(F.col("node").alias("src"), F.col("node").alias("dst"))).distinct()
    n = 0
    while True:
        reach = settled(reach.join(reach.select(F.col("src").alias("dst"), F.col("dst").alias("x")), "dst").select("src", F.col("x").alias("dst")).distinct(), "reach")
        now = reach.count()
        if now == n:
            break
        n = now
    both = reach.join(reach.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"])
    return both.groupBy(F.col("src").alias("node")).agg(F.min("dst").alias("comp"))


def chain_moves(edges: DataFrame, p: DataFrame, conn: DataFrame, paths: DataFrame, hops: int) -> DataFrame:
    """(path, hop, v, g): the best node of every hop of some paths (path, hop, a, b), with the moves of earlier hops counted.

    Every node of a hop's block can go, one that has just come too; ties go to smaller ids. Tables are the paths' and, for a
    hop, a row for each node of its block; what earlier moves change is a row for each neighbour of a moved node.
    """
    near, done = symmetric(edges), None
    for hop in range(1, hops + 1):
        step = F.broadcast(paths.where(F.col("hop") == hop).select("path", "a", F.col("b").alias("to")))
        here = p.join(step, F.col("b") == F.col("a")).select("path", "v", "a", "to")
        if done is not None:
            last = done.groupBy("path", "v").agg(F.max_by("b", "hop").alias("now"))
            come = last.join(step, "path").where("now = a").select("path", "v", "a", "to")
            here = here.join(F.broadcast(last), ["path", "v"], "left_anti").unionByName(come)
        signed = F.when(F.col("x") == F.col("to"), F.col("w")).when(F.col("x") == F.col("a"), -F.col("w")).otherwise(0).alias("g")
        rows = here.select("path", "v", F.lit(0).cast("long").alias("g"), F.lit(True).alias("here"))
        rows = rows.unionByName(here.join(conn.select("v", F.col("b").alias("x"), "w"), "v").where("x in (a, to)").select("path", "v", signed, F.lit(True).alias("here")))
        if done is not None:
            moved = F.broadcast(done.select("path", F.col("v").alias("nbr"), F.col("a").alias("old"), F.col("b").alias("new")))
            change = near.join(moved, "nbr").select("path", "v", F.explode(F.array(F.struct(F.col("old").alias("x"), (-F.col("w")).alias("w")), F.struct(F.col("new").alias("x"), F.col("w").alias("w")))).alias("c"))
            change = change.select("path", "v", "c.x", "c.w").join(step, "path")
            rows = rows.unionByName(change.select("path", "v", signed, F.lit(False).alias("here")))
        best = rows.groupBy("path", "v").agg(F.sum("g").alias("g"), F.max("here").alias("here")).where("here").groupBy("path").agg(F.max(F.struct("g", (-F.col("v")).alias("v"))).alias("m"))
        one = best.join(step, "path").select("path", F.lit(hop).alias("hop"), "a", F.col("to").alias("b"), (-F.col("m.v")).alias("v"), F.col("m.g").alias("g"))
        one = settled(one) if hop < hops else one
        done = one if done is None else done.unionByName(one)
    return done.select("path", "hop", "v", "g")
