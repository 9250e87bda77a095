"""Registered queries: every method, variant, baseline, measure, workload and operator, with SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import cycles as C
from ..functions import graphs as GR
from ..functions import measures as M
from ..functions import models as MO
from ..functions import starts as ST
from ..operators import multilevel as ML
from ..operators import refine as RF
from ..operators.baselines import optimum
from ..operators.local import Arc, conflict
from ..schema import PRESETS, BalanceSpec, Graph, RefineConfig
from ..sources import derive
from ..sources import files as FI
from ..sources.scratch import scratch_path, settled
from ..streaming import edges as SE
from . import experiments as X
from . import sql as Q
from . import surface as SU

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


class Case:
    """A graph, a start partition and the bound of one query."""

    def __init__(self, spark, sf, graph="order_chain", kind="round_robin", k=4, eps="0"):
        self.spark, self.sf, self.k = spark, sf, k
        self.g = graph if isinstance(graph, Graph) else derive.graph(spark, sf, graph)
        self.n = self.g.nodes.count()
        self.spec = BalanceSpec.of(k, self.n, eps)
        self.p = X.start(self.g, kind, k, self.n, spark, sf)

    @property
    def conn(self):
        return M.connections(self.g.edges, self.p)

    @property
    def gain(self):
        return M.gains(self.conn)

    @property
    def blocks(self):
        return M.blocks(self.g, self.p, self.spec)


# --- Graphs

for _name in derive.GRAPHS:
    query(Q.EDGES[_name], f"q_graph_{_name}")(lambda spark, sf, name=_name: derive.graph(spark, sf, name).edges.select("u", "v", "w"))


@query(f"with e as ({Q.EDGES['order_chain']}), s as (select u as v, w from e union all select v, w from e) select n.v, cast(count(s.v) as bigint) as degree, cast(coalesce(sum(w), 0) as bigint) as weight from ({Q.NODES['order_chain']}) n left join s on s.v = n.v group by 1")
def q_degree(spark, sf):
    return GR.degrees(derive.graph(spark, sf, "order_chain"))


@query(f"with recursive e as materialized ({Q.EDGES['document_overlap']}), s as materialized (select u as a, v as b from e union select v, u from e), r(v, x) as (select v, v from ({Q.NODES['document_overlap']}) union select r.v, s.b from r join s on s.a = r.x) select v, min(x) as comp from r group by 1")
def q_components(spark, sf):
    return GR.components(derive.graph(spark, sf, "document_overlap"))


_LEVELS = "".join(f", d{i} as materialized (select * from d{i - 1} union select nbr, {i} from s join d{i - 1} on d{i - 1}.v = s.v where nbr not in (select v from d{i - 1}))" for i in range(1, 7))


@query(f"with e as ({Q.EDGES['order_chain']}), s as materialized (select u as v, v as nbr from e union all select v, u from e), d0 as (select min(v) as v, 0 as level from ({Q.NODES['order_chain']})){_LEVELS} select v, cast(min(level) as int) as level from d6 group by v")
def q_bfs_levels(spark, sf):
    g = derive.graph(spark, sf, "order_chain")
    return GR.levels(g.edges, g.nodes.agg(F.min("v").alias("v")), 6)


@query(f"with e as ({Q.EDGES['nation_trade']}) select u as v, v as nbr, w from e union all select v, u, w from e")
def q_symmetric(spark, sf):
    return GR.symmetric(derive.graph(spark, sf, "nation_trade").edges)


@query(Q.base(kind="chunk") + "select u, v, w from placed where bu = 0 and bv = 0")
def q_induced(spark, sf):
    c = Case(spark, sf, kind="chunk")
    return GR.induced(c.g.edges, c.p.where("b = 0"))


# --- Starts, sizes, balance

for _kind in ("chunk", "round_robin", "mod_hash", "skewed"):
    query(Q.start("order_chain", _kind, 8), f"q_part_{_kind}")(lambda spark, sf, kind=_kind: Case(spark, sf, kind=kind, k=8).p)


@query("select n_nationkey::bigint as v, n_regionkey::int as b from nation")
def q_part_attribute(spark, sf):
    return ST.attribute(derive.read(spark, sf, "nation"), "n_nationkey", "n_regionkey")


@query(Q.base(kind="skewed") + "select b, size, cap, over from blocks")
def q_block_sizes(spark, sf):
    return Case(spark, sf, kind="skewed").blocks


_BALANCE = Q.base(kind="skewed") + "select cast(sum(size) as bigint) as n, cast(max(size + cap - over) as bigint) as lmax, max(size) as largest, cast(sum(over) as bigint) as overload, count(*) filter (where size = 0) as empty, max(over) = 0 as feasible, round(max(size) / ((sum(size) + 3) // 4) - 1, 9) as imbalance from blocks"


def _balance(columns: str, name: str):
    @query(f"select {columns} from ({_BALANCE})", name)
    def run(spark, sf):
        c = Case(spark, sf, kind="skewed")
        return M.balance(c.g, c.p, c.spec).selectExpr(*columns.split(", "))


_balance("n, overload, empty", "q_overload")
_balance("largest, imbalance", "q_imbalance")
_balance("lmax, feasible", "q_feasible")


@query("select k, n % k = 0 as divisible, (n + k - 1) // k as lmax from (select count(*) as n from orders), (select unnest([2, 4, 8, 16, 32, 64]) as k)")
def q_divisible(spark, sf):
    n = derive.read(spark, sf, "orders").count()
    return spark.createDataFrame([(k, BalanceSpec.of(k, n).divisible, BalanceSpec.of(k, n).lmax) for k in (2, 4, 8, 16, 32, 64)], "k int, divisible boolean, lmax long")


# --- Cut, quotient, gains


@query(Q.base() + "select cast(sum(w) filter (where bu <> bv) as bigint) as cut, cast(sum(w) as bigint) as total from placed")
def q_cut(spark, sf):
    c = Case(spark, sf)
    return M.placed(c.g.edges, c.p).agg(F.sum(F.when(F.col("bu") != F.col("bv"), F.col("w"))).alias("cut"), F.sum("w").alias("total"))


_QUOTIENT = "select least(bu, bv) as a, greatest(bu, bv) as b, cast(sum(w) as bigint) as w, count(*) as m from placed where bu <> bv group by 1, 2"


@query(Q.base(k=8) + _QUOTIENT)
def q_quotient(spark, sf):
    c = Case(spark, sf, k=8)
    return M.quotient(c.g.edges, c.p)


@query(Q.base(k=8) + f"select w from ({_QUOTIENT}) where a = 0 and b = 1")
def q_pair_cut(spark, sf):
    c = Case(spark, sf, k=8)
    return M.quotient(c.g.edges, c.p).where("a = 0 and b = 1").select("w")


@query(Q.base(kind="chunk") + "select u, v, w, bu, bv from placed where bu <> bv")
def q_cut_edges(spark, sf):
    c = Case(spark, sf, kind="chunk")
    return M.cut_edges(c.g.edges, c.p)


@query(Q.base(kind="chunk", more=f", p2 as ({Q.start('order_chain', 'chunk', 8)}), c1 as (select u, v, w from placed where bu <> bv), c2 as (select e.u, e.v, w from e join p2 x on x.v = e.u join p2 y on y.v = e.v where x.b <> y.b)") + "select *, 'first' as side from (select * from c1 except all select * from c2) union all select *, 'second' from (select * from c2 except all select * from c1)")
def q_cut_diff(spark, sf):
    c, d = Case(spark, sf, kind="chunk"), Case(spark, sf, kind="chunk", k=8)
    return M.cut_diff(c.g.edges, c.p, d.p)


@query(Q.base() + "select v, own, b, w from conn")
def q_connections(spark, sf):
    return Case(spark, sf).conn


@query(Q.base() + "select v, a, b, g from gain")
def q_gain(spark, sf):
    return Case(spark, sf).gain


@query(Q.base(kind="chunk") + "select distinct v from conn where b <> own")
def q_boundary(spark, sf):
    return M.boundary(Case(spark, sf, kind="chunk").conn)


@query(Q.base() + "select a, b, cast(r as int) as rank, v, g from (select *, row_number() over (partition by a, b order by g desc, v) as r from gain) where r <= 3")
def q_top_gain_per_pair(spark, sf):
    return M.top_gains(Case(spark, sf).gain, 3)


_CENSUS = [(g, s, k) for g in ("order_chain", "event_handoff", "embedding_knn") for s in ("chunk", "round_robin") for k in (4, 8)]


@query(" union all ".join(f"select * from ({Q.base(g, s, k)} select '{g}' as graph, '{s}' as start, {k} as k, count(*) as boundary, count(*) filter (where g > 0) as positive, max(g) as best from (select v, max(g) as g from gain group by v))" for g, s, k in _CENSUS))
def q_positive_gain_census(spark, sf):
    out, graphs = None, {g: derive.graph(spark, sf, g) for g in {x[0] for x in _CENSUS}}
    for g, s, k in _CENSUS:
        c = Case(spark, sf, graphs[g], s, k)
        part = M.positive_gain(c.g, c.p).select(F.lit(g).alias("graph"), F.lit(s).alias("start"), F.lit(k).alias("k"), "*")
        out = part if out is None else out.unionByName(part)
    return out


# --- Basic model


def _lex(spark, sf, k=4, **case):
    c = Case(spark, sf, k=k, **case)
    engine = RF.Parallel(c.g, c.p, c.spec, RefineConfig(model="basic", order="lex", tie="lex"))
    return c, engine.basic_searches(0)


@query(Q.base(more=Q.picks(4)) + "select a, b, v, g from picks")
def q_basic_candidates_ordered(spark, sf):
    _, found = _lex(spark, sf)
    return spark.createDataFrame([(s.a, s.b, s.nodes[0], s.gains[0]) for s in found], "a int, b int, v long, g long")


@query(Q.base(more=Q.picks(4)) + "select a as src, b as dst, -g as w from picks")
def q_basic_model(spark, sf):
    _, found = _lex(spark, sf)
    return spark.createDataFrame([(s.a, s.b, -s.gains[0]) for s in found], "src int, dst int, w long")


@query(Q.base(kind="skewed") + "select -1 as src_b, 0 as src_d, b as dst_b, 1 as dst_d, cast(0 as bigint) as w, 'source' as kind from blocks union all select b, 1, -1, 0, 0, 'return' from blocks where cap > 0")
def q_source_returns(spark, sf):
    b = Case(spark, sf, kind="skewed").blocks
    return MO.source_arcs(b, 1).unionByName(MO.return_arcs(b, 1))


def _shifted(spark, sf, k=8):
    """Quotient arcs with negative weights but no negative cycle: weights shifted by labels of the blocks."""
    c = Case(spark, sf, k=k)
    q = M.quotient(c.g.edges, c.p)
    both = q.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w").unionByName(q.select(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))
    h = lambda x: (17 * F.col(x)) % 5
    arcs = both.select("src", "dst", (F.when((F.col("src") + F.col("dst")) % 2 == 1, 0).otherwise(F.col("w")) + h("src") - h("dst")).cast("long").alias("w"))
    return arcs, spark.range(k).select(F.col("id").cast("int").alias("node"))


@query(Q.base(k=8, more=Q.model(8)) + "select node, pi from l8")
def q_potentials(spark, sf):
    return MO.potentials(*_shifted(spark, sf), 8)[0]


@query(Q.base(k=8, more=Q.model(8)) + "select src, dst, w, l from ell")
def q_reduced_arcs(spark, sf):
    arcs, nodes = _shifted(spark, sf)
    return MO.reduced_arcs(arcs, MO.potentials(arcs, nodes, 8)[0])


@query(Q.base(k=8, more=Q.model(8)) + "select src, dst from ell where l = 0")
def q_zero_subgraph(spark, sf):
    arcs, nodes = _shifted(spark, sf)
    return MO.reduced_arcs(arcs, MO.potentials(arcs, nodes, 8)[0]).where("l = 0").select("src", "dst")


_SCC = ", r0 as (select src, dst from ell where l = 0 union select node, node from l0)" + "".join(f", r{i} as materialized (select distinct x.src, y.dst from r{i - 1} x join r{i - 1} y on y.src = x.dst)" for i in range(1, 4))


@query(Q.base(k=8, more=Q.model(8) + _SCC) + "select x.src as node, min(x.dst) as comp from r3 x join r3 y on y.src = x.dst and y.dst = x.src group by 1")
def q_scc(spark, sf):
    arcs, nodes = _shifted(spark, sf)
    return MO.strong_components(MO.reduced_arcs(arcs, MO.potentials(arcs, nodes, 8)[0]).where("l = 0"), nodes)


_TOP = ", top as materialized (select a, b, max(g) as g from gain group by 1, 2)"


@query(Q.base(k=8, more=_TOP) + "select max(x.g + y.g) as gain from top x join top y on x.b = y.a and y.b = x.a where x.a < x.b")
def q_best_two_cycle(spark, sf):
    t = M.top_gains(Case(spark, sf, k=8).gain).select("a", "b", "g")
    back = t.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("g").alias("g2"))
    return t.join(back, ["a", "b"]).where("a < b").agg(F.max(F.col("g") + F.col("g2")).alias("gain"))


@query(Q.base(k=8, more=_TOP) + "select max(x.g + y.g + z.g) as gain from top x join top y on x.b = y.a join top z on y.b = z.a and z.b = x.a where x.a <> y.b and x.a < x.b and x.a < y.b")
def q_best_three_cycle(spark, sf):
    t = M.top_gains(Case(spark, sf, k=8).gain).select("a", "b", "g")
    y, z = t.toDF("b", "c", "g2"), t.toDF("c", "a", "g3")
    return t.join(y, "b").join(z, ["c", "a"]).where("a <> c and a < b and a < c").agg(F.max(F.col("g") + F.col("g2") + F.col("g3")).alias("gain"))


_PATHS = ", paths(first, last, seen, g) as (select a, b, [a, b], g from top union all select first, t.b, list_append(seen, t.b), paths.g + t.g from paths join top t on t.a = paths.last where (not list_contains(seen, t.b) or t.b = first) and last <> first)"


@query(Q.base(kind="chunk", more=_TOP + _PATHS).replace("with e", "with recursive e", 1) + "select coalesce(max(g), 0) > 0 as negative from paths where last = first")
def q_has_negative_cycle(spark, sf):
    rows = M.top_gains(Case(spark, sf, kind="chunk").gain).collect()
    found = C.negative_cycle(4, [r["a"] for r in rows], [r["b"] for r in rows], [-r["g"] for r in rows])[1]
    return spark.createDataFrame([(found is not None,)], "negative boolean")


# --- Searches and the layered model


@query(Q.base(kind="chunk", more=Q.searches()) + "select a, b, d, v, g from searches")
def q_dsearch_tau2(spark, sf):
    c = Case(spark, sf, kind="chunk")
    return MO.unmarked_searches(c.g.edges, c.p, 2)


_THREE = """, w0 as (select v, g from gain where a = 1 and b = 0 order by g desc, v limit 1),
inA as materialized (select p.v, coalesce(y.w, 0) - coalesce(x.w, 0) as g from p left join conn x on x.v = p.v and x.b = 1 left join conn y on y.v = p.v and y.b = 0 where p.b = 1),
w1 as materialized (select i.v, i.g + 2 * sum(s.w) as g from inA i join s on s.v = i.v and s.nbr in (select v from w0) where i.v not in (select v from w0) group by i.v, i.g order by 2 desc, 1 limit 1),
m1 as materialized (select v from w0 union all select v from w1),
w2 as materialized (select i.v, i.g + 2 * sum(s.w) as g from inA i join s on s.v = i.v and s.nbr in (select v from m1) where i.v not in (select v from m1) group by i.v, i.g order by 2 desc, 1 limit 1)"""


@query(Q.base(kind="chunk", more=_THREE) + "select 1 as d, v, g from w0 union all select 2, w1.v, cast(w0.g + w1.g as bigint) from w0, w1 union all select 3, w2.v, cast(w0.g + w1.g + w2.g as bigint) from w0, w1, w2")
def q_dsearch_tau3(spark, sf):
    c = Case(spark, sf, kind="chunk")
    engine = RF.Parallel(c.g, c.p, c.spec, RefineConfig(tie="lex"))
    seeds = settled(engine.seeds(M.gains(engine.conn).where("a = 1 and b = 0"), None, 0), "seeds")
    return engine.speculated(seeds, None, 3, 0).select("d", "v", "g")


def _layers(spark, sf):
    """Searches on a start of which some blocks have room, and its blocks."""
    c = Case(spark, sf, kind="chunk", k=7)
    return MO.unmarked_searches(c.g.edges, c.p, 2).select("a", "b", "d", "g"), c.blocks


_SKEW = Q.base(kind="chunk", k=7, more=Q.searches())


@query(_SKEW + "select a as src_b, d as src_d, b as dst_b, d as dst_d, -g as w, 'move' as kind from searches")
def q_layered_arcs(spark, sf):
    return MO.layer_arcs(_layers(spark, sf)[0])


@query(_SKEW + "select b as src_b, 1 as src_d, b as dst_b, 2 as dst_d, cast(0 as bigint) as w, 'up' as kind from blocks")
def q_up_arcs(spark, sf):
    return MO.up_arcs(_layers(spark, sf)[1], 2)


@query(_SKEW + "select a as src_b, 2 as src_d, searches.b as dst_b, 1 as dst_d, -g as w, 'down' as kind from searches join blocks on blocks.b = searches.b and cap > 0 where d = 2")
def q_down_arcs(spark, sf):
    return MO.down_arcs(*_layers(spark, sf))


@query(_SKEW + "select b as src_b, d as src_d, -1 as dst_b, 0 as dst_d, cast(0 as bigint) as w, 'return' as kind from blocks, (select unnest([1, 2]) as d) where cap >= d")
def q_return_arcs(spark, sf):
    return MO.return_arcs(_layers(spark, sf)[1], 2)


@query(Q.base(more=", two as (select a, b, 1 as d, row_number() over (partition by a, b order by g desc, v) as sid, g from gain)") + "select a, b, d, arg_max(sid, (g, -sid)) as sid, max(g) as g from two where sid <= 2 group by 1, 2, 3")
def q_best_per_layer(spark, sf):
    two = M.top_gains(Case(spark, sf).gain, 2).select("a", "b", F.lit(1).alias("d"), F.col("rank").cast("long").alias("sid"), "g")
    return MO.best_per_layer(two)


#: Blocks of the arcs that an order's lines are read as; block b has room for b % 3 nodes.
ARC_BLOCKS = 8
#: A line moves 1 to 3 nodes from one block to another.
_LINE = f"l_orderkey as c, cast(l_suppkey % {ARC_BLOCKS} as int) as a, cast((l_suppkey + 1 + l_partkey % {ARC_BLOCKS - 1}) % {ARC_BLOCKS} as int) as b, cast(l_linenumber % 3 + 1 as int) as d"


@query(
    f"with m as (select {_LINE} from lineitem), "
    "t as (select c, count(*) > least(count(distinct a), count(distinct b)) as repeated from m group by c), "
    "f as (select c, b, sum(d) as d from (select c, b, d from m union all select c, a, -d from m) group by c, b), "
    "o as (select c, max(d - b % 3) > 0 as over from f where d > 0 group by c) "
    "select t.c as cycle, case when repeated then 'repeat' when coalesce(over, false) then 'overload' else 'ok' end as kind from t left join o on o.c = t.c"
)
def q_conflict_kinds(spark, sf):
    """The lines of each order as moves of one step."""
    view = RF.Blocks(BalanceSpec(ARC_BLOCKS, 14 * ARC_BLOCKS), {b: 14 - b % 3 for b in range(ARC_BLOCKS)})
    moves = {d: tuple(range(d)) for d in (1, 2, 3)}

    def kinds(batches):
        for batch in batches:
            out = []
            for lines in batch.column(1).to_pylist():
                arcs = [Arc(0, 0, 0, "move", x["a"], x["b"], moves[x["d"]], (i,)) for i, x in enumerate(lines)]
                out.append(conflict(arcs, view) or "ok")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], names=["cycle", "kind"])

    lines = derive.read(spark, sf, "lineitem").selectExpr(*_LINE.split(", ")).groupBy("c").agg(F.collect_list(F.struct("a", "b", "d")).alias("lines"))
    return lines.mapInArrow(kinds, "cycle long, kind string")


# --- Balance

_RELAX = _TOP + ", z0 as (select b as node, cast(0 as bigint) as pi from blocks where over > 0)" + "".join(f", z{i} as materialized (select node, min(pi) as pi from (select * from z{i - 1} union all select b, pi - g from top join z{i - 1} on node = a) group by 1)" for i in range(1, 5))


@query(Q.base(kind="skewed", more=_RELAX) + "select min(pi) as cost from z4 join blocks on b = node where cap > 0")
def q_balance_path_tau1(spark, sf):
    c = Case(spark, sf, kind="skewed")
    top = M.top_gains(c.gain).select(F.col("a").alias("src"), F.col("b").alias("dst"), (-F.col("g")).alias("w"))
    b = c.blocks
    d = MO.distances(top, b.where("over > 0").select(F.col("b").alias("node")), 4)
    return d.join(b.where("cap > 0").select(F.col("b").alias("node")), "node").agg(F.min("pi").alias("cost"))


_FOREST = ", adj as (select distinct a, b from gain), f0 as (select b, 0 as level from blocks where over > 0)" + "".join(f", f{i} as materialized (select b, min(level) as level from (select * from f{i - 1} union all select adj.b, level + 1 from adj join f{i - 1} x on x.b = adj.a) group by b)" for i in range(1, 5))


@query(Q.base(kind="skewed", more=_FOREST) + "select b, cast(level as int) as level from f4")
def q_forest(spark, sf):
    c = Case(spark, sf, kind="skewed")
    q = M.quotient(c.g.edges, c.p).select(F.col("a").cast("long").alias("u"), F.col("b").cast("long").alias("v"), "w")
    return GR.levels(q, c.blocks.where("over > 0").select(F.col("b").cast("long").alias("v")), 4).select(F.col("v").cast("int").alias("b"), "level")


_CHAIN = """, every as materialized (select p.v, p.b as a, q.b, coalesce(o.w, 0) - coalesce(i.w, 0) as g from p join blocks q on q.b <> p.b
  left join conn o on o.v = p.v and o.b = q.b left join conn i on i.v = p.v and i.b = p.b),
lead as materialized (select a, b, v, g from (select *, row_number() over (partition by a, b order by g desc, v) as r from every) where r = 1),
adj as (select distinct a, b from gain),
ways as (select i.a as x, i.b as y, j.b as z from adj i join adj j on j.a = i.b join blocks s on s.b = i.a join blocks t on t.b = j.b where s.over > 0 and t.cap > 0 and i.a <> j.b),
follow as (select x, y, z, l.v as v1, l.g as g1, r.v as v2, r.g - coalesce(e.w, 0) as g2 from ways join lead l on l.a = x and l.b = y join every r on r.a = y and r.b = z left join s e on e.v = l.v and e.nbr = r.v
  union all select x, y, z, l.v, l.g, l.v, coalesce(o.w, 0) - coalesce(i.w, 0) from ways join lead l on l.a = x and l.b = y left join conn o on o.v = l.v and o.b = z left join conn i on i.v = l.v and i.b = y)
"""


@query(Q.base(kind="skewed", more=_CHAIN) + "select x, y, z, v1, v2, cast(-(g1 + g2) as bigint) as cost from (select *, row_number() over (partition by x, y, z order by g2 desc, v2) as r from follow) where r = 1")
def q_chain_costs(spark, sf):
    """All chains of two single moves from an overloaded block over another to one with room."""
    c = Case(spark, sf, kind="skewed")
    conn = settled(c.conn)
    pairs, b = M.gains(conn).select("a", "b").distinct(), c.blocks
    ways = pairs.select(F.col("a").alias("x"), F.col("b").alias("y")).join(pairs.select(F.col("a").alias("y"), F.col("b").alias("z")), "y").where("x <> z")
    ways = ways.join(b.where("over > 0").select(F.col("b").alias("x")), "x").join(b.where("cap > 0").select(F.col("b").alias("z")), "z").select("x", "y", "z", F.struct("x", "y", "z").alias("path"))
    ways = settled(ways)
    steps = ways.select("path", F.lit(1).alias("hop"), F.col("x").alias("a"), F.col("y").alias("b")).unionByName(ways.select("path", F.lit(2).alias("hop"), F.col("y").alias("a"), F.col("z").alias("b")))
    moves = MO.chain_moves(c.g.edges, c.p, conn, steps, 2)
    return moves.groupBy("path").agg(*(F.max(F.when(F.col("hop") == h, F.col("v"))).alias(f"v{h}") for h in (1, 2)), (-F.sum("g")).alias("cost")).select("path.x", "path.y", "path.z", "v1", "v2", "cost")


# --- Moves

_MOVES = ", moves as materialized (select v, any_value(a) as old_b, cast(min(b) as int) as new_b from (select *, row_number() over (partition by a, b order by g desc, v) as r from gain) where r = 1 group by v)"


def _moves(c: Case) -> DataFrame:
    return M.top_gains(c.gain).groupBy("v").agg(F.min("a").alias("old_b"), F.min("b").alias("new_b"))


_AFTER = ", after as materialized (select p.v, coalesce(new_b, b) as b from p left join moves on moves.v = p.v)"


@query(Q.base(more=_MOVES + _AFTER) + "select v, b from after")
def q_apply_moves(spark, sf):
    c = Case(spark, sf)
    return M.apply_moves(c.p, _moves(c))


@query(Q.base(more=_MOVES + _AFTER) + "select s.v, o.b as own, t.b, cast(sum(w) as bigint) as w from s join after o on o.v = s.v join after t on t.v = s.nbr group by 1, 2, 3")
def q_delta_connections(spark, sf):
    c = Case(spark, sf)
    return M.apply_delta(c.conn, c.g.edges, _moves(c))


@query(Q.base("nation_trade_sparse", "mod_hash", 5, _TOP.replace("top", "unused")) + "select a.a, a.b, max(a.g + z.g - 2 * coalesce(e.w, 0)) as gain from (select t.v as v, t.own as a, t.b, coalesce(o.w, 0) - coalesce(i.w, 0) as g from (select p.v, p.b as own, q.b from p join blocks q on q.b <> p.b) t left join conn o on o.v = t.v and o.b = t.b left join conn i on i.v = t.v and i.b = t.own) a join (select t.v as v, t.own as b, t.b as a, coalesce(o.w, 0) - coalesce(i.w, 0) as g from (select p.v, p.b as own, q.b from p join blocks q on q.b <> p.b) t left join conn o on o.v = t.v and o.b = t.b left join conn i on i.v = t.v and i.b = t.own) z on z.a = a.a and z.b = a.b left join e on e.u = least(a.v, z.v) and e.v = greatest(a.v, z.v) where a.a < a.b group by 1, 2")
def q_swap_best(spark, sf):
    """The best exchange of every pair of blocks, by a join on the pair; for graphs of few nodes."""
    c = Case(spark, sf, "nation_trade_sparse", "mod_hash", 5)
    conn = c.conn
    targets = c.p.select("v", F.col("b").alias("a")).join(F.broadcast(spark.range(5).select(F.col("id").cast("int").alias("b"))), F.col("a") != F.col("b"))
    inner = conn.where("b = own").select("v", F.col("w").alias("i"))
    g = targets.join(conn.select("v", "b", F.col("w").alias("o")), ["v", "b"], "left").join(inner, "v", "left").select("v", "a", "b", (F.coalesce("o", F.lit(0)) - F.coalesce("i", F.lit(0))).alias("g"))
    back = g.select(F.col("v").alias("y"), F.col("b").alias("a"), F.col("a").alias("b"), F.col("g").alias("h"))
    pairs = g.where("a < b").join(back, ["a", "b"]).join(GR.symmetric(c.g.edges).select("v", F.col("nbr").alias("y"), "w"), ["v", "y"], "left")
    return pairs.groupBy("a", "b").agg(F.max(F.col("g") + F.col("h") - 2 * F.coalesce("w", F.lit(0))).alias("gain"))


# --- Refinement: facts that hold for every seed


def _facts(rows: dict[str, int], spark) -> DataFrame:
    return spark.createDataFrame([(k, int(v)) for k, v in rows.items()], "name string, value long")


def _fact_sql(graph: str, k: int, eps: str = "0") -> str:
    lmax = f"cast(floor({1 + float(eps)} * ((n + {k - 1}) // {k}) + 1e-9) as bigint)"
    return f"select unnest(['n', 'lmax', 'feasible', 'cut_not_worse', 'cut_is_true', 'nodes_kept']) as name, unnest([n, {lmax}, 1, 1, 1, n]) as value from (select count(*) as n from ({Q.NODES[graph]}))"


def _refined(spark, sf, cfg: RefineConfig, graph="order_chain", kind="chunk", k=4, eps="0", seed=1, worse_allowed=False):
    c = Case(spark, sf, graph, kind, k, eps)
    r = RF.refine(c.g, c.p, c.spec, cfg, seed)
    b = M.balance(c.g, r.part, c.spec).first()
    kept = c.g.nodes.join(r.part, "v").count()
    true = M.cut(c.g.edges, r.part)
    return _facts({"n": b["n"], "lmax": b["lmax"], "feasible": b["feasible"], "cut_not_worse": worse_allowed or r.trace["cut_after"] <= r.trace["cut_before"], "cut_is_true": true == r.trace["cut_after"], "nodes_kept": kept}, spark)


for _name, _cfg in PRESETS.items():
    query(_fact_sql("order_chain", 8), f"q_refine_{_name}")(lambda spark, sf, cfg=_cfg: _refined(spark, sf, cfg.but(max_rounds=8, mu=min(cfg.mu, 4)), k=8))
    query(_fact_sql("embedding_knn", 8), f"q_refine_{_name}_embedding")(lambda spark, sf, cfg=_cfg: _refined(spark, sf, cfg.but(max_rounds=8, mu=min(cfg.mu, 4)), "embedding_knn", k=8))
for _name in ("basic_zero", "packed"):
    query(_fact_sql("order_chain", 4), f"q_parallel_{_name}")(lambda spark, sf, cfg=PRESETS[_name]: _refined(spark, sf, cfg.but(engine="parallel", max_rounds=1, mu=1, tau=4), kind="round_robin"))

for _name, _graph in (("skewed", "event_handoff_sparse"), ("disconnected", "conversation_chain")):
    query(_fact_sql(_graph, 4), f"q_parallel_balance_{_name}")(lambda spark, sf, graph=_graph: _refined(spark, sf, PRESETS["basic"].but(engine="parallel", max_rounds=1), graph, "skewed", worse_allowed=True))

query(_fact_sql("order_chain", 8, "0.03"), "q_refine_eps")(lambda spark, sf: _refined(spark, sf, PRESETS["packed"].but(max_rounds=6, mu=2), k=8, eps="0.03"))
query(_fact_sql("event_handoff_sparse", 4), "q_balance_skewed")(lambda spark, sf: _refined(spark, sf, PRESETS["layered"].but(max_rounds=4, lam=1, tau=3), "event_handoff_sparse", "skewed", worse_allowed=True))
query(_fact_sql("conversation_chain", 4), "q_balance_disconnected")(lambda spark, sf: _refined(spark, sf, PRESETS["basic"].but(max_rounds=4, lam=1), "conversation_chain", "skewed", worse_allowed=True))
query(_fact_sql("order_chain", 8), "q_no_interlayer")(lambda spark, sf: _refined(spark, sf, PRESETS["layered"].but(max_rounds=6, interlayer=False), k=8))
query(_fact_sql("order_chain", 8), "q_packed_combination")(lambda spark, sf: _refined(spark, sf, PRESETS["packed"].but(max_rounds=6, mu=3, combine=True), k=8))
query(_fact_sql("nation_trade", 5), "q_swap_polish")(lambda spark, sf: _refined(spark, sf, PRESETS["layered"].but(max_rounds=6, swap_polish=True), "nation_trade", "chunk", 5))
query(_fact_sql("event_handoff_sparse", 4), "q_solver_plain")(lambda spark, sf: _refined(spark, sf, PRESETS["layered"].but(max_rounds=6, solver="plain", harvest=False, mark_scope="touched", candidate_scope="boundary", conflict_rule="distinct_search"), "event_handoff_sparse", "chunk", 4))


@query("select 'longer_cycles' as name, cast(0 as bigint) as value")
def q_two_block_cycles(spark, sf):
    c = Case(spark, sf, kind="chunk", k=2)
    r = RF.refine(c.g, c.p, c.spec, PRESETS["basic_zero"].but(max_rounds=10), 1)
    return _facts({"longer_cycles": sum(n for key, n in r.trace.items() if key.startswith("cycle ") and int(key.split()[-1]) > 2)}, spark)


@query("select 'within_capacity' as name, cast(1 as bigint) as value union all select 'total', cast(sum(l_quantity) as bigint) from lineitem")
def q_weighted_capacity(spark, sf):
    """Node weights: parts weigh their sold quantity; blocks keep their bound in weight."""
    c = Case(spark, sf, "part_coorder_min2", "round_robin", 4)
    weight = derive.read(spark, sf, "lineitem").groupBy(F.col("l_partkey").alias("v")).agg(F.sum("l_quantity").cast("long").alias("c"))
    nodes = c.g.nodes.select("v").join(weight, "v", "left").select("v", F.coalesce("c", F.lit(0)).alias("c"))
    g = Graph(c.g.edges, nodes, "weighted")
    sizes = M.weighted_sizes(g, c.p)
    top = int(sizes.agg(F.max("size")).first()[0] * 1.02)
    r = RF.replay(g, c.p, BalanceSpec(4, 4 * top), PRESETS["basic"].but(max_rounds=4), 1)
    after = M.weighted_sizes(g, r.part).agg(F.max("size").alias("m"), F.sum("size").alias("s")).first()
    return _facts({"within_capacity": after["m"] <= top, "total": after["s"]}, spark)


# --- Tiny graphs

def _enumeration(n: int, k: int, edges: str, nodes: str) -> str:
    """All balanced assignments of n nodes by rank, by cross joins of blocks."""
    size = -(-n // k)
    grow = "a0 as (select [0] as x)" + "".join(f", a{i} as (select list_append(x, b) as x from a{i - 1}, (select unnest(range({k})) as b) where len(list_filter(x, lambda y: y = b)) < {size} and b <= list_max(x) + 1)" for i in range(1, n))
    return f"with {grow}, e as ({edges}), i as (select v, row_number() over (order by v) as i from ({nodes})), t as (select x.i as iu, y.i as iv, w from e join i x on x.v = e.u join i y on y.v = e.v) select min(cut) as cut from (select x, sum(case when x[iu] <> x[iv] then w else 0 end) as cut from a{n - 1}, t group by x)"


_TRIO = "select v from (" + Q.NODES["nation_trade"] + ") order by v limit 12"


@query(_enumeration(12, 3, f"select * from ({Q.EDGES['nation_trade']}) where u in ({_TRIO}) and v in ({_TRIO})", _TRIO))
def q_trio_optimum(spark, sf):
    """The trade of the twelve nations with the smallest keys in three blocks of four."""
    g = derive.graph(spark, sf, "nation_trade")
    few = g.nodes.orderBy("v").limit(12)
    return _optimum(spark, few, GR.induced(g.edges, few).collect(), 12, 3)


def _optimum(spark, nodes: DataFrame, edges: list, n: int, k: int) -> DataFrame:
    """The least cut into k equal blocks; null, as in the SQL, where no edge has both its ends among the nodes."""
    at = {r["v"]: i for i, r in enumerate(nodes.orderBy("v").collect())}
    u, v = ([at[r[x]] for r in edges] for x in ("u", "v"))
    return spark.createDataFrame([(optimum(n, u, v, [r["w"] for r in edges], k, -(-n // k))[0] if edges else None,)], "cut long")


_TINY = "select v from (" + Q.NODES["supplier_coorder"] + ") order by v limit 10"


@query(_enumeration(10, 2, f"select * from ({Q.EDGES['supplier_coorder']}) where u in ({_TINY}) and v in ({_TINY})", _TINY))
def q_tiny_optimum(spark, sf):
    """The ten suppliers with the smallest keys: a graph small enough for exact search."""
    g = derive.graph(spark, sf, "supplier_coorder")
    few = g.nodes.orderBy("v").limit(10)
    rows = GR.induced(g.edges, few).collect()
    return _optimum(spark, few, rows, 10, 2)


# --- Multilevel and evolution


@query("select unnest(['self_matched_twice', 'not_adjacent', 'coarse_over_half']) as name, unnest([0, 0, 0]) as value")
def q_matching_valid(spark, sf):
    g = derive.graph(spark, sf, "embedding_knn")
    m = ML.match(g)
    groups = m.groupBy("cv").agg(F.count("*").alias("n"), F.max("v").alias("x")).where("n > 1")
    apart = groups.select(F.col("cv").alias("u"), F.col("x").alias("v")).join(g.edges, ["u", "v"], "left_anti").count()
    return _facts({"self_matched_twice": groups.where("n > 2").count(), "not_adjacent": apart, "coarse_over_half": int(groups.count() * 2 > g.nodes.count())}, spark)


@query(f"with e as ({Q.EDGES['order_chain']}) select 'weight' as name, cast(sum(w) as bigint) as value from e union all select 'nodes', count(*) from orders")
def q_contract_conserves(spark, sf):
    g = derive.graph(spark, sf, "order_chain")
    m = ML.match(g)
    small = ML.contract(g, m)
    inner = M.placed(g.edges, m.select("v", F.col("cv").alias("b"))).where("bu = bv").agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    return _facts({"weight": inner + small.edges.agg(F.sum("w")).first()[0], "nodes": small.nodes.agg(F.sum("c")).first()[0]}, spark)


def _campaign_facts(grid, work):
    def run(spark, sf):
        r = X.campaign(spark, sf, grid, work).agg(F.count("*").alias("runs"), F.count_if(F.col("largest") <= F.col("lmax")).alias("feasible"), F.count_if(F.col("overload_after") == 0).alias("balanced"))
        return r.selectExpr("stack(3, 'runs', runs, 'feasible', feasible, 'balanced', balanced) as (name, value)")

    return run


def _all_sql(n: int) -> str:
    return f"select unnest(['runs', 'feasible', 'balanced']) as name, unnest([{n}, {n}, {n}]) as value"


_ML = [("multilevel", "embedding_knn", k, 0.0, 1, "basic:max_rounds=4", "chunk") for k in (2, 4, 8)]
query(_all_sql(len(_ML)), "q_multilevel")(_campaign_facts(_ML, "balance_cost"))
_EV = [("scratch", "embedding_knn", k, e, 1, "packed:max_rounds=4,mu=3", s) for k, e, s in ((4, 0.0, "new"), (4, 0.03, "new"), (4, 0.0, "seeded"))]
query(_all_sql(len(_EV)), "q_evolve")(_campaign_facts(_EV, "scratch"))
query(_all_sql(1), "q_population_feasible")(_campaign_facts(_EV[:1], "scratch"))
_WB = [("guarantee", g, k, 0.0, 1, "basic:max_rounds=4,lam=1", "skewed") for g, k in (("conversation_chain", 4), ("event_handoff_sparse", 4), ("document_overlap", 4))]
query(_all_sql(len(_WB)), "q_guarantee")(_campaign_facts(_WB, "improve"))


# --- Experiment tables (rows only: they hold times and random choices)


@query()
def q_improved_table(spark, sf):
    grid = [("improve", g, k, 0.0, 1, f"{c}:max_rounds=12,lam=4,mu={m}", "chunk+swap") for g in ("order_chain", "embedding_knn") for k in (2, 4, 8) for c, m in (("basic", 1), ("basic_zero", 1), ("layered", 1), ("packed", 4))]
    return X.improved_table(X.campaign(spark, sf, grid, "improve").withColumn("config", F.substring_index("config", ":", 1)))


@query()
def q_vs_reference(spark, sf):
    grid = [("scratch", "embedding_knn", k, e, 1, "packed:max_rounds=4,mu=3", "new") for k in (2, 4, 8) for e in (0.0, 0.01, 0.03, 0.05)]
    return X.vs_reference(X.campaign(spark, sf, grid, "scratch"))


@query()
def q_balance_cost(spark, sf):
    grid = [("balance", "embedding_knn", k, 0.0, s, "packed:max_rounds=6,mu=4", "chunk") for k in (2, 4, 8, 16) for s in (1, 2, 3)]
    return X.cost_table(X.campaign(spark, sf, grid, "balance_cost"))


@query()
def q_sweep(spark, sf):
    grid = [("sweep", "embedding_knn", 4, 0.0, 1, f"packed:max_rounds=6,tau={t},mu={m},lam={x}", "chunk") for t in (1, 7, 15) for m in (1, 5) for x in (1, 3)]
    return X.campaign(spark, sf, grid, "improve").select("config", "cut_before", "cut_after", "conflicts", "cycles", "secs")


@query()
def q_all_levels(spark, sf):
    grid = [("levels", "embedding_knn", 4, 0.0, 1, "layered:max_rounds=4", "chunk")]
    return X.campaign(spark, sf, grid, "all_levels").select("graph", "k", "cut_before", "cut_after", "base_secs", "secs")


@query()
def q_conflict_rate(spark, sf):
    grid = [("conflicts", g, k, 0.0, 1, "packed:max_rounds=6,mu=3", "chunk") for g, k in (("order_chain", 8), ("event_handoff_sparse", 4), ("embedding_knn", 8))]
    return X.campaign(spark, sf, grid, "improve", spread=True).select("graph", "k", "conflicts", "cycles")


@query()
def q_baselines(spark, sf):
    grid = [("baselines", "embedding_knn", 4, 0.0, 1, c, s) for c, s in (("none", "chunk"), ("swap", "chunk"), ("labels", "chunk"), ("none", "random"), ("packed:max_rounds=6,mu=3", "chunk"))]
    return X.campaign(spark, sf, grid, "improve").select("config", "cut_before", "cut_after", "largest", "lmax", "secs")


# --- Relational surface


@query(Q.base(k=4) + "select bu, bv, cast(sum(w) as bigint) as w from placed group by rollup (bu, bv)")
def q_rollup_cut(spark, sf):
    c = Case(spark, sf)
    return M.placed(c.g.edges, c.p).rollup("bu", "bv").agg(F.sum("w").alias("w"))


@query(Q.base(kind="chunk", more=f", p2 as ({Q.start('order_chain', 'round_robin', 4)})") + "select p.b as b1, p2.b as b2, count(*) as n from p join p2 on p2.v = p.v group by cube (p.b, p2.b)")
def q_cube_sizes(spark, sf):
    a, b = Case(spark, sf, kind="chunk"), Case(spark, sf)
    return a.p.select("v", F.col("b").alias("b1")).join(b.p.select("v", F.col("b").alias("b2")), "v").cube("b1", "b2").agg(F.count("*").alias("n"))


@query("select o_orderstatus as s, o_orderpriority as p, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def q_grouping_sets(spark, sf):
    derive.read(spark, sf, "orders").createOrReplaceTempView("bc_orders")
    return spark.sql("select o_orderstatus as s, o_orderpriority as p, count(*) as n from bc_orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")


@query(Q.base(more=", best as (select v, arg_max(b, (g, -b)) as b, max(g) as g from gain where g > 0 group by v)") + "select v, b, g, row_number() over (partition by b order by g desc, v) as place from best")
def q_window_prefix_capacity(spark, sf):
    best = Case(spark, sf).gain.where("g > 0").groupBy("v").agg(F.max_by("b", F.struct(F.col("g"), -F.col("b"))).alias("b"), F.max("g").alias("g"))
    return best.withColumn("place", F.count("*").over(Window.partitionBy("b").orderBy(F.desc("g"), "v").rowsBetween(Window.unboundedPreceding, 0)))


@query(Q.base(more=_MOVES) + "select v from p where v not in (select v from moves union all select nbr from s where v in (select v from moves))")
def q_semi_eligible(spark, sf):
    c = Case(spark, sf)
    moved = _moves(c).select("v")
    closed = moved.unionByName(GR.symmetric(c.g.edges).join(moved, "v", "left_semi").select(F.col("nbr").alias("v")))
    return c.p.select("v").join(closed, "v", "left_anti")


@query(f"with e as ({Q.EDGES['part_coorder_min2']}) select v from ({Q.NODES['part_coorder_min2']}) where v not in (select u from e union all select v from e)")
def q_anti_isolated(spark, sf):
    return GR.isolated(derive.graph(spark, sf, "part_coorder_min2"))


@query(Q.base(kind="chunk", more=f", p2 as ({Q.start('order_chain', 'chunk', 8)})") + "select u, v, w from placed where bu <> bv intersect select e.u, e.v, w from e join p2 x on x.v = e.u join p2 y on y.v = e.v where x.b <> y.b")
def q_setops_cut_edges(spark, sf):
    c, d = Case(spark, sf, kind="chunk"), Case(spark, sf, kind="chunk", k=8)
    return M.cut_edges(c.g.edges, c.p).select("u", "v", "w").intersect(M.cut_edges(d.g.edges, d.p).select("u", "v", "w"))


@query(Q._EDGE.format("select user_id as a, b from (select user_id, lead(user_id) over w as b, ts, lead(ts) over w as ts2 from events window w as (order by ts, event_id)) where date_diff('microsecond', ts, ts2) < 1801 * 1000000"))
def q_interval_handoff(spark, sf):
    return derive.event_handoff(spark, sf, 30).edges.select("u", "v", "w")


@query("select o.event_id, max(e.ts) as last_login from events o left join events e on e.user_id = o.user_id and e.ts <= o.ts and e.event_type = 'click' where o.event_type = 'purchase' group by 1")
def q_asof_handoff(spark, sf):
    """The latest click of the user before each purchase, by one window over both."""
    ev = derive.read(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    seen = F.last(F.when(F.col("event_type") == "click", F.col("ts")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0))
    return ev.withColumn("last_login", seen).where("event_type = 'purchase'").select("event_id", "last_login")


@query("select event_id, json_extract_string(props, '$.' || (json_keys(props)[1])) as first_value, len(json_keys(props)) as n_keys from events")
def q_json_props(spark, sf):
    ev = derive.read(spark, sf, "events").select("event_id", "props", F.json_object_keys("props").alias("k"))
    return ev.select("event_id", F.expr("element_at(from_json(props, 'map<string,string>'), k[0])").alias("first_value"), F.size("k").cast("long").alias("n_keys"))


@query("select token, count(*) as n from (select unnest(regexp_extract_all(html, 'href=\"/([^/\"?#]+)', 1)) as token from pages) group by 1")
def q_regex_links(spark, sf):
    return derive.read(spark, sf, "pages").select(F.explode_outer(F.regexp_extract_all("html", F.lit('href="/([^/"?#]+)'), F.lit(1))).alias("token")).where("token is not null").groupBy("token").agg(F.count("*").alias("n"))


@query(f"with e as ({Q.EDGES['nation_trade_sparse']}), s as (select u as v, v as nbr from e union all select v, u from e) select v, string_agg(nbr, ',' order by nbr) as nbrs from s group by v")
def q_array_neighbours(spark, sf):
    n = GR.neighbour_lists(derive.graph(spark, sf, "nation_trade_sparse").edges)
    return n.select("v", F.array_join(F.transform("nbrs", lambda x: x["nbr"].cast("string")), ",").alias("nbrs"))


@query(Q.base() + "select a, b, v, g from gain order by g desc, v, b limit 20")
def q_topk_arcs(spark, sf):
    return Case(spark, sf).gain.orderBy(F.desc("g"), "v", "b").limit(20).select("a", "b", "v", "g")


@query()
def q_approx_degree(spark, sf):
    return GR.symmetric(derive.graph(spark, sf, "customer_supplier").edges).groupBy("v").agg(F.approx_count_distinct("nbr").alias("degree"))


@query(Q.base(kind="chunk", more=f", p2 as ({Q.start('order_chain', 'round_robin', 4)})") + "select p.b as b1, p2.b as b2, count(*) as n from p join p2 on p2.v = p.v group by 1, 2")
def q_overlap(spark, sf):
    return M.overlap(Case(spark, sf, kind="chunk").p, Case(spark, sf).p)


@query(f"with e as materialized ({Q.EDGES['order_chain']}), t as (select x.u as a, x.v as b, y.v as c from e x join e y on y.u = x.v join e z on z.u = x.u and z.v = y.v) select v, count(*) as n from (select a as v from t union all select b from t union all select c from t) group by v")
def q_triangles(spark, sf):
    return GR.triangles(derive.graph(spark, sf, "order_chain").edges)


# --- Files and SQL surface


@query(f"select kind, u, v, w from ({Q.EDGES['order_chain']}) cross join (select unnest(['adjacency', 'csv', 'json', 'orc', 'parquet']) as kind)")
def q_edge_files(spark, sf):
    """Edges as they come back from each format."""
    edges, out = derive.graph(spark, sf, "order_chain").edges, None
    for kind in ("adjacency", *FI.FORMATS):
        path = scratch_path(spark, f"edges-{kind}")
        FI.write_edges(edges, path, kind, buckets=4)
        back = FI.read_edges(spark, path, kind).select(F.lit(kind).alias("kind"), "u", "v", "w")
        out = back if out is None else out.unionByName(back)
    return out


@query(Q.base() + "select v, b from p where b = 1")
def q_partition_files(spark, sf):
    """One block of a stored partition; the other blocks' folders aren't read."""
    path = scratch_path(spark, "partition")
    FI.write_partition(Case(spark, sf).p, path)
    return FI.read_partition(spark, path).where("b = 1")


@query(Q.base() + "select a, b, v, g from gain where g > 1")
def q_sql_arcs(spark, sf):
    c = Case(spark, sf)
    SU.register(spark, c.g, c.p, c.spec)
    return spark.sql("select a, b, v, g from graph_arcs_above(1)")


@query(Q.base() + "select 'bound' as name, cast((count(*) + 3) // 4 as bigint) as value from p union all select 'cut', cast(coalesce(sum(w), 0) as bigint) from placed where (bu = 0 and bv = 1) or (bu = 1 and bv = 0)")
def q_sql_functions(spark, sf):
    c = Case(spark, sf)
    SU.register(spark, c.g, c.p, c.spec)
    return spark.sql("select 'bound' as name, graph_bound(n, 4, 0, 1) as value from (select count(*) as n from graph_nodes) union all select 'cut', cut from graph_cut_of(1, 0)")


# --- Streams


@query("select date_trunc('day', ts) as start, user_id, event_type, count(*) as w from events group by 1, 2, 3")
def q_stream_windowed_edges(spark, sf):
    out = SE.drain(SE.windowed_edges(SE.events(spark, sf)), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


_SESSION = "with x as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end as new from events), y as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as s from x)"


@query(_SESSION + " select user_id, min(ts) as start, max(ts) + interval 6 hours as \"end\", count(*) as n from y group by user_id, s")
def q_stream_session(spark, sf):
    out = SE.drain(SE.sessions(SE.events(spark, sf)), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "n")


@query("with u as (select user_id, (row_number() over (order by user_id) - 1) % 4 as b from (select distinct user_id from events)), n as (select count(*) as n, min(user_id) as lo from u) select date_trunc('day', ts) as start, cast(sum(case when x.b <> y.b then 1 else 0 end) as bigint) as cut, count(*) as total from events e join u x on x.user_id = e.user_id join n on true join u y on y.user_id = lo + e.event_id % n.n group by 1")
def q_stream_live_cut(spark, sf):
    c = Case(spark, sf, "event_handoff")
    low = c.g.nodes.agg(F.min("v")).first()[0]
    stream = SE.events(spark, sf).withColumn("peer", F.lit(low) + F.col("event_id") % c.n)
    out = SE.drain(SE.live_cut(stream, c.p), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query()
def q_stream_late_dropped(spark, sf):
    """In append mode only windows that the watermark has closed are written; later rows for them are dropped."""
    return SE.drain(SE.windowed_edges(SE.events(spark, sf), watermark="10 minutes"), "append")


def entry(spark: SparkSession, sf: str) -> DataFrame:
    """The flagship: order chain, round robin start with four blocks, a few basic rounds."""
    c = Case(spark, sf)
    r = RF.refine(c.g, c.p, c.spec, PRESETS["basic_zero"].but(max_rounds=6), 1)
    facts = M.balance(c.g, r.part, c.spec)
    return facts.select(F.lit(r.trace["cut_before"]).cast("long").alias("cut_before"), F.lit(r.trace["cut_after"]).cast("long").alias("cut_after"), "n", "lmax", "largest", "overload", "feasible")
