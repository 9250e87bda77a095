"""Helpers of the corpus operators: shared scratch tables, fixed-size key masks, text spans."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of all word rules here (fixed values).
SPACE_CLASS = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Only where the session names none (tests on one machine) a temporary folder is made.
    """
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="balcut-")
        sc.setCheckpointDir(root)
    return root.rstrip("/")


_TO_FORGET: set[str] = set()


def _at_exit(spark: SparkSession) -> None:
    with contextlib.suppress(Exception):  # the session may have ended already
        forget(spark)


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder; everything of this application there goes when the driver ends."""
    if spark.sparkContext.applicationId not in _TO_FORGET:
        _TO_FORGET.add(spark.sparkContext.applicationId)
        atexit.register(_at_exit, spark)
    return f"{scratch_root(spark)}/balcut/{spark.sparkContext.applicationId}/{label}-{uuid.uuid4().hex}"


def settle(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    The lineage ends there, so a lost executor costs a reread and never a recomputation, and
    generated keys stay as they were written.
    """
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession) -> None:
    """Delete every scratch table of this application."""
    jvm = spark._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{scratch_root(spark)}/balcut/{spark.sparkContext.applicationId}")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def blank_split(text: Column) -> Column:
    """The text's words and some empty strings.

    All white space becomes a blank first: splitting at one plain character is faster than at a class.
    """
    flat = F.coalesce(text, F.lit(""))
    for c in "\t\n\v\f\r":
        flat = F.replace(flat, F.lit(c), F.lit(" "))
    return F.split(flat, " ", -1)


def words_of(text: Column) -> Column:
    """Array of the maximal runs of characters that aren't white space."""
    return F.array_remove(blank_split(text), "")


def each(column: Column) -> Column:
    """``explode`` for computed arrays; rows of empty arrays give null, which callers drop.

    From a plain ``explode`` the optimizer infers a filter on the array's size and evaluates the
    whole expression a second time, in lambdas once per element.
    """
    return F.explode_outer(column)


def fenced(df: DataFrame) -> DataFrame:
    """Adds ``_fence``: filters that also name it aren't pushed below and evaluated once more there."""
    return df.withColumn("_fence", F.monotonically_increasing_id())


def sealed(df: DataFrame) -> DataFrame:
    """``df`` whose columns are computed once: no filter above is pushed below and evaluates them again."""
    row = F.when(F.monotonically_increasing_id() >= 0, F.struct(*(F.col(f"`{c}`") for c in df.columns)))
    return df.select(row.alias("_row")).select(*(F.col("_row").getField(c).alias(c) for c in df.columns))


def unused(df: DataFrame, *names: str) -> list[str]:
    """The names, each with underscores put in front until no column of ``df`` has it."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name)
        out.append(name)
    return out


#: Parts that a hot key is dealt over.
SALTS = 16


def dealt(big: DataFrame, small: DataFrame, key: Column, hot: DataFrame, hot_key: Column, by: Column, salt: str = "_salt", salts: int = SALTS) -> tuple[DataFrame, DataFrame]:
    """Both sides of an inner join with a column ``salt`` to join on besides their key.

    ``key`` hashes the join key on either side. Rows of ``big`` with a hot key are dealt by ``by`` over some
    salts, and their partners in ``small`` repeated for each. A fixed-size mask tells hot keys on both sides.
    """
    mask = key_mask(hot, hot_key)
    left = big.withColumn(salt, F.when(in_mask(mask, key), F.pmod(by, F.lit(salts)).cast("int")).otherwise(F.lit(0)))
    every = F.sequence(F.lit(0), F.when(in_mask(mask, key), F.lit(salts - 1)).otherwise(F.lit(0)))
    return left, small.withColumn(salt, F.explode(every))


MASK_BITS = 1 << 20


def key_mask(keys: DataFrame, hashed: Column, bits: int = MASK_BITS) -> Column:
    """A scalar subquery: array of ``bits / 64`` longs with a bit set for every key's hash.

    Its size is fixed by ``bits`` and doesn't grow with the keys. More keys only let more rows
    through; the exact join that follows decides.
    """
    spark = keys.sparkSession
    slots = bits // 64
    at = F.pmod(hashed, F.lit(bits))
    ones = keys.select((at / 64).cast("int").alias("slot"), F.call_function("shiftleft", F.lit(1).cast("long"), (at % 64).cast("int")).alias("bit"))
    dense = spark.range(slots).select(F.col("id").cast("int").alias("slot")).join(ones.groupBy("slot").agg(F.bit_or("bit").alias("bit")), "slot", "left")
    packed = F.transform(F.sort_array(F.collect_list(F.struct("slot", F.coalesce("bit", F.lit(0).cast("long")).alias("bit")))), lambda s: s["bit"])
    return dense.agg(packed.alias("mask")).scalar()


def in_mask(mask: Column, hashed: Column, bits: int = MASK_BITS) -> Column:
    at = F.pmod(hashed, F.lit(bits))
    return F.getbit(F.get(mask, (at / 64).cast("int")), (at % 64).cast("int")) == 1


def running_start(lengths: Column, block: int = 128) -> Column:
    """For an array of ints, the sum of all elements before each one.

    Blocks keep the work near linear: a sum over earlier blocks and one within the block.
    """
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / block).cast("int")), lambda b: F.slice(lengths, b * block + 1, block))
    sums = F.transform(cut, lambda x: F.aggregate(x, F.lit(0), lambda a, e: a + e))
    based = F.transform(cut, lambda x, b: F.struct(x.alias("x"), F.aggregate(F.slice(sums, 1, b), F.lit(0), lambda a, e: a + e).alias("base")))
    flat = F.flatten(F.transform(based, lambda s: F.transform(s["x"], lambda _, i: s["base"] + F.aggregate(F.slice(s["x"], 1, i), F.lit(0), lambda a, e: a + e))))
    return F.when(F.size(lengths) > 0, flat).otherwise(F.array().cast("array<int>"))


def with_matches(df: DataFrame, text: str, patterns: dict[str, tuple[str, Column]]) -> DataFrame:
    """Add, for each name, an array of (start, end, value) of the leftmost non-overlapping matches.

    ``patterns`` has for each name a regular expression and a cheap condition that every text
    with a match fulfils. Starts and ends count code points, ends are exclusive. Spark has no
    function for the places of matches, so they come from the lengths of the pieces between
    them, which the same expression splits off.
    """
    for name, (regex, may) in patterns.items():
        df = df.withColumn(f"_{name}_m", F.when(may, F.regexp_extract_all(F.col(text), F.lit(regex), F.lit(0))).otherwise(F.array().cast("array<string>")))
    for name, (regex, _) in patterns.items():
        gaps = F.transform(F.split(F.col(text), regex, -1), F.length)
        df = df.withColumn(f"_{name}_g", F.when(F.size(f"_{name}_m") > 0, gaps).otherwise(F.array().cast("array<int>")))
    for name in patterns:
        both = F.transform(F.col(f"_{name}_m"), lambda m, i: F.get(F.col(f"_{name}_g"), i) + F.length(m))
        df = df.withColumn(f"_{name}_l", both)
    for name in patterns:
        df = df.withColumn(f"_{name}_p", running_start(F.col(f"_{name}_l")))
    for name in patterns:
        spans = F.transform(
            F.col(f"_{name}_m"),
            lambda m, i: F.struct(
                (F.get(F.col(f"_{name}_p"), i) + F.get(F.col(f"_{name}_g"), i)).alias("start"),
                (F.get(F.col(f"_{name}_p"), i) + F.get(F.col(f"_{name}_l"), i)).alias("end"),
                m.alias("value"),
            ),
        )
        df = df.withColumn(name, spans)
    return df.drop(*(f"_{name}_{x}" for name in patterns for x in "mglp"))


SPAN = "array<struct<start:int,rank:int,end:int,kind:string,value:string>>"


def tagged(spans: Column, kind: str, rank: int) -> Column:
    """Spans with their kind and its place in the listed order, in the order of sorting."""
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("rank"), s["end"].alias("end"), F.lit(kind).alias("kind"), s["value"].alias("value"))).cast(SPAN)


def span_text(spans: Column) -> Column:
    """``kind:start:end`` of sorted spans, joined by commas."""
    return F.array_join(F.transform(F.array_sort(spans), lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


CUT_BLOCK = 4096


def cut_out(text: Column, spans: Column, put: str = "label") -> Column:
    """``text`` with each of the sorted, disjoint ``spans`` replaced by its field ``put``.

    The text is cut into blocks of one length first, so a piece costs its own length and a block or two,
    wherever it stands in the text.
    """
    n = F.size(spans)
    before = lambda i: F.when(i == 0, F.lit(0)).otherwise(F.get(spans, i - 1)["end"])

    def cut(blocks: Column) -> Column:
        inside = lambda k: F.coalesce(F.get(blocks, k), F.lit(""))

        def part(start: Column, end: Column) -> Column:
            first, last = F.floor(start / CUT_BLOCK).cast("int"), F.floor((end - 1) / CUT_BLOCK).cast("int")
            head = F.substring(inside(first), start % CUT_BLOCK + 1, F.least(end - start, F.lit(CUT_BLOCK)))
            middle = F.array_join(F.slice(blocks, first + 2, F.greatest(last - first - 1, F.lit(0))), "")
            tail = F.substring(inside(last), F.lit(1), end - last * CUT_BLOCK)
            return F.when(end <= start, F.lit("")).when(first == last, head).otherwise(F.concat(head, middle, tail))

        pieces = F.transform(spans, lambda s, i: F.concat(part(before(i), s["start"]), s[put]))
        return F.concat(F.array_join(pieces, ""), part(F.get(spans, n - 1)["end"], F.length(text)))

    # The blocks are the variable of a lambda, so they are made once and not for every span.
    blocks = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{CUT_BLOCK}}}"), F.lit(0))
    return F.when(n > 0, F.get(F.transform(F.array(blocks), cut), 0)).otherwise(text)


def merged(spans: Column) -> Column:
    """Sorted spans with overlapping ones joined; each keeps the kind of its first part."""
    empty = F.array().cast("array<struct<start:int,end:int,kind:string>>")

    def add(done: Column, s: Column) -> Column:
        last = F.element_at(done, -1)
        kept = F.slice(done, 1, F.size(done) - 1)
        joined = F.struct(last["start"].alias("start"), F.greatest(last["end"], s["end"]).alias("end"), last["kind"].alias("kind"))
        own = F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))
        return F.when((F.size(done) > 0) & (F.get(done, F.size(done) - 1)["end"] > s["start"]), F.concat(kept, F.array(joined))).otherwise(F.concat(done, F.array(own)))

    return F.aggregate(F.array_sort(spans), empty, add)
