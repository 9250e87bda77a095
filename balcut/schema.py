"""Table schemas, the balance rule, and the configuration of the refinement methods."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField(c, T.LongType()) for c in ("u", "v", "w")])
NODES = T.StructType([T.StructField(c, T.LongType()) for c in ("v", "c")])
PART = T.StructType([T.StructField("v", T.LongType()), T.StructField("b", T.IntegerType())])
ARCS = T.StructType(
    [T.StructField(c, T.IntegerType()) for c in ("src_b", "src_d", "dst_b", "dst_d")]
    + [T.StructField("w", T.LongType()), T.StructField("kind", T.StringType()), T.StructField("sid", T.LongType()), T.StructField("d", T.IntegerType())]
)


class SchemaError(ValueError):
    """A table isn't a graph or partition."""


class InfeasibleBalance(ValueError):
    """No partition of these nodes keeps the bound."""


@dataclass(frozen=True)
class BalanceSpec:
    """k blocks of at most floor((1 + eps) * ceil(n / k)) nodes; eps is kept as a fraction."""

    k: int
    n: int
    eps: Fraction = Fraction(0)

    @classmethod
    def of(cls, k: int, n: int, eps: float | str | Fraction = 0) -> BalanceSpec:
        return cls(k, n, eps if isinstance(eps, Fraction) else Fraction(str(eps)))

    @property
    def lmax(self) -> int:
        return int((1 + self.eps) * -(-self.n // self.k))

    @property
    def divisible(self) -> bool:
        return self.n % self.k == 0


@dataclass(frozen=True)
class RefineConfig:
    """Options of the refinement methods; ``tau`` None means 15 up to 8 blocks and 7 beyond."""

    model: str = "layered"
    tau: int | None = None
    mu: int = 20
    lam: int = 3
    zero_cycles: bool = True
    interlayer: bool = True
    conflict_rule: str = "simple_block"
    mark_scope: str = "moved"
    candidate_scope: str = "pair"
    order: str = "hash"
    tie: str = "hash"
    solver: str = "subtree"
    harvest: bool = True
    engine: str | None = None
    swap_polish: bool = False
    combine: bool = False
    max_rounds: int = 50
    budget_s: float | None = None
    local_edge_limit: int = 2_000_000

    def steps(self, k: int) -> int:
        return 1 if self.model == "basic" else self.tau or (15 if k <= 8 else 7)

    def but(self, **changes) -> RefineConfig:
        return replace(self, **changes)


#: The four compared configurations; each adds one thing to the one before.
PRESETS = {
    "basic": RefineConfig(model="basic", zero_cycles=False, mu=1),
    "basic_zero": RefineConfig(model="basic", zero_cycles=True, mu=1),
    "layered": RefineConfig(model="layered", mu=1),
    "packed": RefineConfig(model="layered", mu=20),
}


@dataclass
class Graph:
    """An undirected graph: edges (u < v, w > 0, unique) and all nodes with their weights."""

    edges: DataFrame
    nodes: DataFrame
    name: str = "graph"
    facts: dict = field(default_factory=dict)


def check_graph(g: Graph) -> None:
    """One pass over each table: ids in order, positive weights, no repeats, all ends known."""
    for df, want in ((g.edges, EDGES), (g.nodes, NODES)):
        have = {f.name: f.dataType for f in df.schema.fields}
        if any(have.get(f.name) != f.dataType for f in want.fields):
            raise SchemaError(f"{g.name}: expected {want.simpleString()}, found {df.schema.simpleString()}")
    e = g.edges.agg(F.count_if(~(F.col("u") < F.col("v")) | (F.col("w") <= 0) | F.isnull("u") | F.isnull("v") | F.isnull("w")).alias("bad")).first()
    twice = g.edges.groupBy("u", "v").count().where("count > 1").limit(1).count()
    lost = g.edges.select(F.explode(F.array("u", "v")).alias("v")).join(g.nodes, "v", "left_anti").limit(1).count()
    if e["bad"] or twice or lost:
        raise SchemaError(f"{g.name}: {e['bad']} bad edges, repeated edges: {bool(twice)}, unknown ends: {bool(lost)}")


def check_partition(g: Graph, p: DataFrame, k: int) -> None:
    """Total and single valued: every node exactly once, blocks within 0..k-1."""
    row = g.nodes.join(p, "v", "full").agg(F.count("*").alias("rows"), F.count_if(F.isnull("b") | F.isnull("c") | (F.col("b") < 0) | (F.col("b") >= k)).alias("bad"), F.count_distinct("v").alias("nodes")).first()
    if row["bad"] or row["rows"] != row["nodes"]:
        raise SchemaError(f"{g.name}: not a partition into {k} blocks: {row.asDict()}")
