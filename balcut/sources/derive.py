"""Weighted graphs derived from the given tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.graphs import canonical, heaviest, min_weight
from ..functions.order import ranked, successors
from ..schema import Graph
from .scratch import settled

#: Second kinds of nodes start here.
OFFSET = 10**9
#: Neighbours of a vector, digits of its similarity.
NEAREST, DIGITS = 8, 6
#: Most vectors of which one copy is sent to every executor; more are taken in blocks.
VECTORS_AT_ONCE = 50_000
#: Vectors that a task compares at once, with how many others; and from how many on they are dealt over all cores.
QUERIES_AT_ONCE, TILE, VECTORS_SPREAD = 256, 2048, 5_000
LINE_CHARS, LINE_DOCS = 40, (2, 50)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _nodes(df: DataFrame, *columns) -> DataFrame:
    out = None
    for c in columns:
        part = df.select(F.col(c).cast("long").alias("v")) if isinstance(c, str) else df.select(c.cast("long").alias("v"))
        out = part if out is None else out.unionByName(part)
    return out.distinct().select("v", F.lit(1).cast("long").alias("c"))


def nation_trade(spark, sf):
    line = read(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    order = read(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    buyer = read(spark, sf, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("a"))
    seller = read(spark, sf, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("b"))
    pairs = line.join(order, "l_orderkey").join(buyer, "o_custkey").join(seller, "l_suppkey")
    return Graph(canonical(pairs, "a", "b", None), _nodes(read(spark, sf, "nation"), "n_nationkey"), "nation_trade")


def _coorder(spark, sf, column):
    """Pairs within an order; an order has few lines, so pairs stay near the number of lines."""
    one = read(spark, sf, "lineitem").select("l_orderkey", F.col(column).alias("x")).distinct()
    pairs = one.withColumnRenamed("x", "a").join(one.withColumnRenamed("x", "b"), "l_orderkey").where("a < b")
    return canonical(pairs, "a", "b", None)


def supplier_coorder(spark, sf):
    return Graph(_coorder(spark, sf, "l_suppkey"), _nodes(read(spark, sf, "supplier"), "s_suppkey"), "supplier_coorder")


def part_coorder(spark, sf):
    return Graph(_coorder(spark, sf, "l_partkey"), _nodes(read(spark, sf, "part"), "p_partkey"), "part_coorder")


def part_coorder_min2(spark, sf):
    return Graph(min_weight(_coorder(spark, sf, "l_partkey"), 2), _nodes(read(spark, sf, "part"), "p_partkey"), "part_coorder_min2")


def order_chain(spark, sf):
    """Next order of the customer, and next order overall; days are the buckets of the overall order."""
    orders = read(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    own = orders.select(F.col("o_orderkey").alias("a"), F.lead("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("b"))
    every = successors(orders, F.to_date("o_orderdate"), "o_orderkey", "o_orderdate", "o_orderkey").select(F.col("o_orderkey").alias("a"), F.col("next").alias("b"))
    pairs = own.unionByName(every).where("b is not null")
    return Graph(canonical(pairs, "a", "b", None), _nodes(orders, "o_orderkey"), "order_chain")


def event_handoff(spark, sf, max_gap_minutes: int | None = None):
    """Consecutive events of different users; optionally only within a gap of some minutes."""
    events = read(spark, sf, "events").select("event_id", "user_id", "ts")
    nxt = successors(events, F.to_date("ts"), "event_id", "ts", "event_id")
    later = events.select(F.col("event_id").alias("next"), F.col("user_id").alias("b"), F.col("ts").alias("ts2"))
    pairs = nxt.where("next is not null").join(events.withColumnRenamed("user_id", "a"), "event_id").join(later, "next")
    if max_gap_minutes is not None:
        pairs = pairs.where(F.timestamp_diff("SECOND", "ts", "ts2") <= 60 * max_gap_minutes)
    return Graph(canonical(pairs, "a", "b", None), _nodes(events, "user_id"), "event_handoff")


def customer_supplier(spark, sf):
    line = read(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    order = read(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("a"))
    pairs = line.join(order, "l_orderkey").withColumn("b", F.col("l_suppkey") + OFFSET)
    nodes = _nodes(read(spark, sf, "customer"), "c_custkey").unionByName(_nodes(read(spark, sf, "supplier"), F.col("s_suppkey") + OFFSET))
    return Graph(canonical(pairs, "a", "b", None), nodes, "customer_supplier")


def order_part(spark, sf):
    pairs = read(spark, sf, "lineitem").select(F.col("l_orderkey").alias("a"), (F.col("l_partkey") + OFFSET).alias("b"))
    nodes = _nodes(read(spark, sf, "orders"), "o_orderkey").unionByName(_nodes(read(spark, sf, "part"), F.col("p_partkey") + OFFSET))
    return Graph(canonical(pairs, "a", "b", None), nodes, "order_part")


def _unit(column) -> np.ndarray:
    """The vectors of an Arrow column of lists, scaled to length 1, as rows of an array."""
    m = column.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(column), -1)
    return m / np.linalg.norm(m, axis=1, keepdims=True)


def _nearest(q_ids, q, ids, m, nearest: int):
    """(a, b, s): the nearest of each query by rounded similarity, ties to smaller ids; sorted ``ids`` and ``m`` are the other side.

    Similarities are taken in tiles. A query's bound is the least of its best ones in the first tile, later raised; only what
    reaches it before rounding is rounded and sorted.
    """
    slack, held, bound = 10.0**-DIGITS, [], np.full(len(q), -np.inf)
    for a in range(0, len(ids), TILE):
        sim = q @ m[a : a + TILE].T
        own = np.searchsorted(ids[a : a + TILE], q_ids)
        mine = np.flatnonzero((own < sim.shape[1]) & (ids[np.minimum(a + own, len(ids) - 1)] == q_ids))
        sim[mine, own[mine]] = -np.inf
        if a == 0 and sim.shape[1] > nearest:
            bound = np.partition(sim, -nearest, axis=1)[:, -nearest]
        row, at = np.nonzero(sim >= (bound - slack)[:, None])
        held.append((row, ids[a + at], sim[row, at]))
        if sum(len(x[0]) for x in held) > 4 * nearest * len(q):
            held = [_best(*(np.concatenate(x) for x in zip(*held, strict=True)), nearest)]
            full = np.bincount(held[0][0], minlength=len(q)) >= nearest
            least = np.full(len(q), np.inf)
            np.minimum.at(least, held[0][0], held[0][2])
            bound = np.where(full, np.maximum(bound, least - slack), bound)
    row, b, s = _best(*(np.concatenate(x) for x in zip(*held, strict=True)), nearest)
    keep = s > -np.inf
    return q_ids[row[keep]], b[keep], np.round(s[keep], DIGITS)


def _best(row, ids, sim, nearest: int):
    """The first ``nearest`` of each row by rounded similarity and id."""
    order = np.lexsort((ids, -np.round(sim, DIGITS), row))
    row, ids, sim = row[order], ids[order], sim[order]
    kept = np.arange(len(row)) - np.searchsorted(row, row) < nearest
    return row[kept], ids[kept], sim[kept]


def embedding_knn(spark, sf, nearest: int = NEAREST):
    """Each vector's nearest by cosine. All rows are queries; the other side comes in blocks of a checked size.

    The pairs are written once, as every reader of the graph would compare all vectors again.
    """
    vectors = read(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("v"), F.col("embedding").cast("array<double>").alias("x"))
    n = vectors.count()
    blocks = max(1, -(-n // VECTORS_AT_ONCE))
    found = None
    for k in range(blocks):
        block = vectors.where(F.pmod("v", F.lit(blocks)) == k).toArrow().combine_chunks()
        if not block.num_rows:
            continue
        ids, m = block["v"].to_numpy(), _unit(block["x"].chunk(0))
        order = np.argsort(ids)
        shared = spark.sparkContext.broadcast((ids[order], m[order]))

        def near(batches, shared=shared):
            ids, m = shared.value
            for batch in batches:
                for a in range(0, batch.num_rows, QUERIES_AT_ONCE):
                    some = batch.slice(a, QUERIES_AT_ONCE)
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in _nearest(some.column(0).to_numpy(), _unit(some.column(1)), ids, m, nearest)], names=["a", "b", "s"])

        part = vectors.repartition(4 * spark.sparkContext.defaultParallelism, "v").mapInArrow(near, "a long, b long, s double") if n > VECTORS_SPREAD else vectors.mapInArrow(near, "a long, b long, s double")
        found = part if found is None else found.unionByName(part)
    if blocks > 1:
        found = found.withColumn("_r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(F.col("_r") <= nearest)
    pairs = settled(found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "nearest")
    return Graph(canonical(pairs, "a", "b", None), _nodes(vectors, "v"), "embedding_knn")


def document_overlap(spark, sf):
    """Documents that share a trimmed line of some length which few documents hold."""
    docs = read(spark, sf, "documents").select("doc_id", "text")
    lines = docs.select("doc_id", F.explode_outer(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= LINE_CHARS).distinct()
    rare = lines.groupBy("line").agg(F.count("*").alias("n")).where(F.col("n").between(*LINE_DOCS)).select("line")
    kept = lines.join(rare, "line")
    pairs = kept.withColumnRenamed("doc_id", "a").join(kept.withColumnRenamed("doc_id", "b"), "line").where("a < b")
    return Graph(canonical(pairs, "a", "b", None), _nodes(docs, "doc_id"), "document_overlap")


def page_links(spark, sf):
    """Pages and the first path tokens of their root-relative links."""
    pages = read(spark, sf, "pages").select("page_id", "html")
    links = pages.select("page_id", F.explode_outer(F.regexp_extract_all("html", F.lit('href="/([^/"?#]+)'), F.lit(1))).alias("token")).where("token is not null").distinct()
    tokens = ranked(links.select("token").distinct(), F.substring("token", 1, 2), "token").select("token", (F.col("i") + OFFSET).alias("b"))
    pairs = links.join(tokens, "token").withColumnRenamed("page_id", "a")
    nodes = _nodes(pages, "page_id").unionByName(_nodes(tokens, "b"))
    return Graph(canonical(pairs, "a", "b", None), nodes, "page_links")


def conversation_chain(spark, sf):
    turns = read(spark, sf, "conversations").select("conv_id", "turn")
    node = F.col("conv_id") * 1000 + F.col("turn")
    pairs = turns.select(node.alias("a"), F.lead(node).over(Window.partitionBy("conv_id").orderBy("turn")).alias("b")).where("b is not null")
    return Graph(canonical(pairs, "a", "b", None), _nodes(turns, node), "conversation_chain")


def sparse(base: Graph, c: int = 3) -> Graph:
    return Graph(heaviest(base.edges, c), base.nodes, base.name + "_sparse")


GRAPHS = {f.__name__: f for f in (nation_trade, supplier_coorder, part_coorder, part_coorder_min2, order_chain, event_handoff, customer_supplier, order_part, embedding_knn, document_overlap, page_links, conversation_chain)}
for _base in (nation_trade, supplier_coorder, event_handoff):
    GRAPHS[_base.__name__ + "_sparse"] = lambda spark, sf, base=_base: sparse(base(spark, sf))


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return GRAPHS[name](spark, sf_dir)
