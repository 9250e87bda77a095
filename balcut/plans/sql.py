"""Reference SQL: the derived graphs, start partitions and table measures, for DuckDB."""

from __future__ import annotations

from ..sources.derive import DIGITS, LINE_CHARS, LINE_DOCS, NEAREST, OFFSET

_EDGE = "select least(a, b) as u, greatest(a, b) as v, cast(count(*) as bigint) as w from ({}) where a <> b group by 1, 2"


def _coorder(c: str) -> str:
    one = f"select distinct l_orderkey as o, {c} as x from lineitem"
    return _EDGE.format(f"select p.x as a, q.x as b from ({one}) p join ({one}) q on p.o = q.o and p.x < q.x")


EDGES = {
    "nation_trade": _EDGE.format("select c_nationkey::bigint as a, s_nationkey::bigint as b from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey"),
    "supplier_coorder": _coorder("l_suppkey"),
    "part_coorder": _coorder("l_partkey"),
    "part_coorder_min2": f"select * from ({_coorder('l_partkey')}) where w >= 2",
    "order_chain": _EDGE.format(
        "select o_orderkey as a, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as b from orders "
        "union all select o_orderkey, lead(o_orderkey) over (order by o_orderdate, o_orderkey) from orders"
    ),
    "event_handoff": _EDGE.format("select user_id as a, lead(user_id) over (order by ts, event_id) as b from events"),
    "customer_supplier": _EDGE.format(f"select o_custkey as a, l_suppkey + {OFFSET} as b from lineitem join orders on l_orderkey = o_orderkey"),
    "order_part": _EDGE.format(f"select l_orderkey as a, l_partkey + {OFFSET} as b from lineitem"),
    "embedding_knn": _EDGE.format(
        "select distinct least(p, q) as a, greatest(p, q) as b from (select x.vec_id as p, y.vec_id as q, row_number() over (partition by x.vec_id order by "
        f"round(list_cosine_similarity(x.embedding::double[], y.embedding::double[]), {DIGITS}) desc, y.vec_id) as r from embeddings x join embeddings y on x.vec_id <> y.vec_id) where r <= {NEAREST}"
    ),
    "document_overlap": _EDGE.format(
        "select x.doc_id as a, y.doc_id as b from l x join l y on x.line = y.line and x.doc_id < y.doc_id join r on r.line = x.line"
    ).replace("from (select x.doc_id", f"from (with l as (select distinct doc_id, trim(line) as line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(trim(line)) >= {LINE_CHARS}), r as (select line from l group by line having count(*) between {LINE_DOCS[0]} and {LINE_DOCS[1]}) select x.doc_id"),
    "page_links": f"select page_id as u, t.b as v, cast(1 as bigint) as w from (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"/([^/\"?#]+)', 1)) as token from pages) l join (select token, dense_rank() over (order by token) - 1 + {OFFSET} as b from (select distinct unnest(regexp_extract_all(html, 'href=\"/([^/\"?#]+)', 1)) as token from pages)) t on t.token = l.token",
    "conversation_chain": _EDGE.format("select conv_id * 1000 + turn as a, lead(conv_id * 1000 + turn) over (partition by conv_id order by turn) as b from conversations"),
}
for _name in ("nation_trade", "supplier_coorder", "event_handoff"):
    EDGES[_name + "_sparse"] = (
        f"select distinct least(x, y) as u, greatest(x, y) as v, w from (select x, y, w, row_number() over (partition by x order by w desc, y) as r from (select u as x, v as y, w from ({EDGES[_name]}) union all select v, u, w from ({EDGES[_name]}))) where r <= 3"
    )

NODES = {
    "nation_trade": "select n_nationkey::bigint as v from nation",
    "supplier_coorder": "select s_suppkey as v from supplier",
    "part_coorder": "select p_partkey as v from part",
    "part_coorder_min2": "select p_partkey as v from part",
    "order_chain": "select o_orderkey as v from orders",
    "event_handoff": "select distinct user_id as v from events",
    "embedding_knn": "select vec_id as v from embeddings",
    "document_overlap": "select doc_id as v from documents",
    "conversation_chain": "select distinct conv_id * 1000 + turn as v from conversations",
    "order_part": f"select o_orderkey as v from orders union all select p_partkey + {OFFSET} from part",
    "customer_supplier": f"select c_custkey as v from customer union all select s_suppkey + {OFFSET} from supplier",
}
for _name in ("nation_trade", "supplier_coorder", "event_handoff"):
    NODES[_name + "_sparse"] = NODES[_name]


def start(graph: str, kind: str, k: int) -> str:
    """A start partition (v, b)."""
    if graph == "order_chain":
        ranked = "select o_orderkey as v, row_number() over (order by o_orderdate, o_orderkey) - 1 as i, count(*) over () as n from orders"
        if kind == "skewed":
            ranked = "select o_orderkey as v, row_number() over (order by o_orderkey) - 1 as i, count(*) over () as n from orders"
    else:
        ranked = f"select v, row_number() over (order by v) - 1 as i, count(*) over () as n from ({NODES[graph]})"
    b = {"chunk": f"(i * {k}) // n", "round_robin": f"i % {k}", "skewed": f"case when 10 * i < 6 * n then 0 else i % {k} end", "mod_hash": f"((v * 7919 + 13) % 10007) % {k}"}[kind]
    return f"select v, cast({b} as int) as b from ({ranked})"


def base(graph: str = "order_chain", kind: str = "round_robin", k: int = 4, more: str = "") -> str:
    """Common tables: e edges, p partition, s symmetric edges, conn, gain, blocks."""
    lmax = f"(((select count(*) from p) + {k - 1}) // {k})"
    return f"""with e as materialized ({EDGES[graph]}), p as materialized ({start(graph, kind, k)}),
s as (select u as v, v as nbr, w from e union all select v, u, w from e),
placed as (select e.u, e.v, w, x.b as bu, y.b as bv from e join p x on x.v = e.u join p y on y.v = e.v),
conn as materialized (select s.v, o.b as own, t.b, cast(sum(w) as bigint) as w from s join p o on o.v = s.v join p t on t.v = s.nbr group by 1, 2, 3),
gain as materialized (select v, own as a, b, w - inside as g from (select *, cast(coalesce(sum(case when b = own then w end) over (partition by v), 0) as bigint) as inside from conn) where b <> own),
blocks as materialized (select b, size, greatest({lmax} - size, 0) as cap, greatest(size - {lmax}, 0) as over from
  (select r.b, cast(count(p.v) as bigint) as size from (select cast(range as int) as b from range({k})) r left join p on p.b = r.b group by 1)){more}
"""


def picks(k: int) -> str:
    """Independent candidates of all pairs in the order of (a, b), each blocking itself and its neighbours."""
    out, seen = [], []
    for a in range(k):
        for b in range(k):
            if a == b:
                continue
            name = f"k{a}_{b}"
            free = " ".join(f"and v not in (select v from {x} union all select nbr from s where v in (select v from {x}))" for x in seen)
            out.append(f"{name} as materialized (select a, b, v, g from gain where a = {a} and b = {b} {free} order by g desc, v limit 1)")
            seen.append(name)
    return ", " + ", ".join(out) + ", picks as materialized (" + " union all ".join(f"select * from {x}" for x in seen) + ")"


def model(k: int) -> str:
    """Arcs for potentials: quotient weights shifted by node labels, so negative arcs but no negative cycle."""
    h = lambda x: f"((17 * {x}) % 5)"
    return (
        ", q as (select least(bu, bv) as a, greatest(bu, bv) as b, sum(w) as w from placed where bu <> bv group by 1, 2)"
        f", arcs as materialized (select a as src, b as dst, cast(case when (a + b) % 2 = 1 then 0 else w end + {h('a')} - {h('b')} as bigint) as w from q"
        f" union all select b, a, cast(case when (a + b) % 2 = 1 then 0 else w end + {h('b')} - {h('a')} as bigint) from q)"
        ", l0 as (select cast(range as int) as node, cast(0 as bigint) as pi from range(" + str(k) + "))"
        + "".join(f", l{i} as materialized (select node, min(pi) as pi from (select * from l{i - 1} union all select dst, pi + w from arcs join l{i - 1} on node = src) group by 1)" for i in range(1, k + 1))
        + f", ell as (select src, dst, w, w + x.pi - y.pi as l from arcs join l{k} x on x.node = src join l{k} y on y.node = dst)"
    )


def searches() -> str:
    """Unmarked searches of two steps for all pairs."""
    return """, one as materialized (select a, b, 1 as d, v, g from (select *, row_number() over (partition by a, b order by g desc, v) as r from gain) where r = 1),
near as (select o.a, o.b, s.nbr as v, sum(2 * s.w) as bonus, any_value(o.g) as before from one o join s on s.v = o.v join p on p.v = s.nbr and p.b = o.a group by 1, 2, 3),
cand as (select n.a, n.b, n.v, coalesce(y.w, 0) - coalesce(x.w, 0) + bonus as g, before from near n left join conn x on x.v = n.v and x.b = x.own left join conn y on y.v = n.v and y.b = n.b and y.b <> y.own),
two as (select a, b, 2 as d, v, cast(g + before as bigint) as g from (select *, row_number() over (partition by a, b order by g desc, v) as r from cand) where r = 1),
searches as materialized (select * from one union all select * from two)"""
