"""SimHash near-duplicates with covering locality-sensitive hashing.

Fingerprints have 64 bits. For radius r every bit position gets a non-zero vector of r + 1 bits; table
v keeps the positions whose vector has an odd product with v. The differing positions of two
fingerprints within the radius are at most r vectors, so some v is orthogonal to all of them: the
pair agrees on that table's whole mask. The 2^(r+1) - 1 tables thus miss no pair, unlike random ones.

Equal fingerprints collapse before anything else, so a group of copies is one row. Buckets of two
are compared at once; larger ones are joined in one sweep that gives a spanning forest, never all
pairs; huge ones are dealt once more by masks on the bits the first left free, which bounds a
sub-bucket by 2 to the power of the remaining bits. Components come from alternating large and small stars.

That is op1, whose width and radius are fixed. The pipeline stage takes fingerprints of 5-word shingles in the same
way, and beside them all pairs with a Jaccard similarity of 0.8, most of which differ in more bits than covering masks
can reach: ``near_copies`` finds them through shared rare shingles and checks them by exact counts of common shingles
(equal 64-bit hashes count as equal). Groups of any size are compared in blocks of a bounded one.

Defined results: a null text counts as empty; texts without words have fingerprint 0 and are
linked like any others; repeated rows are in one component; a component's id is its smallest id, null only where
all its ids are; an empty table gives an empty result; texts of any length are hashed in blocks; further columns,
whatever their names, are ignored by the operators and kept by the stage.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import SALTS, each, in_mask, key_mask, settle, table, unused

BITS, SHINGLE, SEED, RADIUS = 64, 3, 42, 3
#: Distinct fingerprints from which a bucket is dealt once more.
LARGE_BUCKET = 4096
#: Bytes of a text that are split into words at once, and hashes that are counted at once.
TEXT_BLOCK, HASH_BLOCK = 1 << 20, 1 << 18
_SPACE = re.compile(rb"[\x20\x09-\x0D]")
#: For a byte, a word with one byte for each of its bits; up to 255 of them add without a carry.
_LANES = np.array([sum(((b >> j) & 1) << (8 * j) for j in range(8)) for b in range(256)], dtype=np.uint64)


def shingle_hashes(text: bytes, width: int = SHINGLE, seed: int = SEED) -> Iterator[list[int]]:
    """Hashes of a text's word shingles, in blocks. bytes.split splits at the six white spaces of the word rule."""
    from xxhash import xxh64_intdigest

    at, carry, any_shingle = 0, [], False
    while at < len(text):
        cut = _SPACE.search(text, min(len(text), at + TEXT_BLOCK))
        end = cut.start() if cut else len(text)
        words = carry + text[at:end].lower().split()
        at = end
        if len(words) >= width:
            any_shingle = True
            flat = b" ".join(words)
            ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
            starts = np.concatenate(([0], ends[:-1] + 1))
            yield [xxh64_intdigest(flat[a:b], seed) for a, b in zip(starts[: len(words) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)]
        carry = words[-(width - 1) :] if any_shingle or len(words) >= width else words
    if not any_shingle and carry:
        yield [xxh64_intdigest(b" ".join(carry), seed)]


def _bit_sums(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """How often each bit is set in each segment of ``hashes``; segments are at most 255 long."""
    octets = hashes.view(np.uint8).reshape(-1, 8)
    return np.concatenate([np.add.reduceat(_LANES[octets[:, k]], starts).view(np.uint8).reshape(-1, 8) for k in range(8)], axis=1)


def fingerprints_of(texts: list[bytes], width: int = SHINGLE) -> np.ndarray:
    """Fingerprints of some texts as signed longs."""
    sums, sizes = np.zeros((len(texts), BITS), np.int64), np.zeros(len(texts), np.int64)
    held: list[list[int]] = []
    rows: list[int] = []
    n = 0

    def count():
        nonlocal held, rows, n
        if not held:
            return
        lengths = np.fromiter(map(len, held), np.int64, len(held))
        flat = np.fromiter((h for part in held for h in part), np.uint64, n)
        first = np.cumsum(lengths) - lengths
        starts = np.concatenate([np.arange(a, a + m, 255) for a, m in zip(first.tolist(), lengths.tolist(), strict=True)])
        owner = np.repeat(rows, -(-lengths // 255))
        np.add.at(sums, owner, _bit_sums(flat, starts))
        np.add.at(sizes, rows, lengths)
        held, rows, n = [], [], 0

    for i, text in enumerate(texts):
        for part in shingle_hashes(text, width):
            for a in range(0, len(part), HASH_BLOCK):
                held.append(part[a : a + HASH_BLOCK])
                rows.append(i)
                n += len(held[-1])
                if n >= HASH_BLOCK:
                    count()
    count()
    bits = (2 * sums > sizes[:, None]).astype(np.uint64)
    return (bits << np.arange(BITS, dtype=np.uint64)).sum(axis=1, dtype=np.uint64).view(np.int64)


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = SHINGLE) -> DataFrame:
    """(doc_id, fp) of every row."""

    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for a in range(0, batch.num_rows, 64):  # a few texts at a time
                part = [x.as_buffer().to_pybytes() for x in texts.slice(a, 64)]
                yield pa.RecordBatch.from_arrays([ids.slice(a, 64), pa.array(fingerprints_of(part, width))], names=["doc_id", "fp"])

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(run, f"doc_id {kind}, fp bigint")


def masks(positions: list[int], radius: int = RADIUS) -> list[int]:
    """The covering masks over some bit positions, as unsigned numbers."""
    space = (1 << (radius + 1)) - 1
    return [sum(1 << p for i, p in enumerate(positions) if ((1 + i % space) & v).bit_count() % 2) for v in range(1, space + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _keys(fp: Column, of: list[int]) -> Column:
    return F.array(*(F.struct(F.lit(v).cast("tinyint").alias("v"), fp.bitwiseAND(F.lit(_signed(m)).cast("long")).alias("key")) for v, m in enumerate(of)))


def _forest(fps: list[int], reps: list[int], radius: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the link graph of some distinct fingerprints: each row is met once."""
    if len(fps) <= 24:
        left, edges = list(range(1, len(fps))), []
        queue = [0]
        while queue:
            x = queue.pop()
            near = [y for y in left if (fps[x] ^ fps[y]).bit_count() <= radius]
            if near:
                edges += [(reps[x], reps[y]) for y in near]
                left = [y for y in left if y not in near]
                queue += near
            elif not queue and left:
                queue.append(left.pop())
        return edges
    f, left, edges = np.array(fps, np.uint64), np.arange(1, len(fps)), []
    queue = [0]
    while queue:
        x = queue.pop()
        hit = np.bitwise_count(f[left] ^ f[x]) <= radius
        if hit.any():
            near = left[hit]
            edges += [(reps[x], reps[y]) for y in near.tolist()]
            left = left[~hit]
            queue += near.tolist()
        if not queue and len(left):
            queue.append(int(left[-1]))
            left = left[:-1]
    return edges


def _linked(members: DataFrame, keys: list[str], radius: int) -> DataFrame:
    """(a, b): spanning edges of every bucket of ``members`` (keys, fp, rep)."""
    dealt = members.select(*keys, "fp", "rep").repartition(*keys).sortWithinPartitions(*keys)
    n = len(keys)

    def run(batches):
        key, fps, reps = None, [], []

        def out():
            edges = _forest(fps, reps, radius) if len(fps) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([e[0] for e in edges], pa.int64()), pa.array([e[1] for e in edges], pa.int64())], names=["a", "b"])

        for batch in batches:
            columns = [batch.column(k).to_pylist() for k in range(n + 2)]
            for *now, fp, rep in zip(*columns, strict=True):
                if now != key:
                    yield out()
                    key, fps, reps = now, [], []
                fps.append(fp & ((1 << 64) - 1))
                reps.append(rep)
        yield out()

    return dealt.mapInArrow(run, "a bigint, b bigint")


def links(reps: DataFrame, radius: int = RADIUS, large: int = LARGE_BUCKET) -> DataFrame:
    """Edges (a, b) between representatives (fp, rep) that keep the connectivity of all links within the radius."""
    of = masks(list(range(BITS)), radius)
    keyed = reps.select("fp", "rep", each(_keys(F.col("fp"), of)).alias("k")).select("fp", "rep", "k.v", "k.key")
    one = F.struct("fp", "rep")
    buckets = settle(keyed.groupBy("v", "key").agg(F.count("*").alias("n"), F.min(one).alias("lo"), F.max(one).alias("hi")).where("n > 1"), "buckets")
    two = buckets.where((F.col("n") == 2) & (F.bit_count(F.col("lo.fp").bitwiseXOR(F.col("hi.fp"))) <= radius)).select(F.col("lo.rep").alias("a"), F.col("hi.rep").alias("b"))
    members = keyed.join(buckets.where("n > 2").select("v", "key", "n"), ["v", "key"])
    middle = _linked(members.where(F.col("n") <= large), ["v", "key"], radius)
    # The rest: masks of the bits that the table's own mask leaves free.
    sub = F.lit(None)
    for v, m in enumerate(of):
        sub = F.when(F.col("v") == v, _keys(F.col("fp"), masks([p for p in range(BITS) if not m >> p & 1], radius))).otherwise(sub)
    deep = members.where(F.col("n") > large).select("v", "key", "fp", "rep", each(sub).alias("s")).where("s is not null").select("v", "key", F.col("s.v").alias("v2"), F.col("s.key").alias("key2"), "fp", "rep")
    return two.unionByName(middle).unionByName(_linked(deep, ["v", "key", "v2", "key2"], radius))


def components(edges: DataFrame) -> DataFrame:
    """(node, component) of every node with an edge: the smallest node it is connected to.

    Alternating large and small stars: a node's larger neighbours, then its smaller ones, move to
    its least neighbour, until only stars are left. Each round is written to the shared folder.
    """

    def state(df):
        row = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return row["n"], row["h"]

    low, high = F.least("a", "b"), F.greatest("a", "b")
    edges = settle(edges.where("a <> b").select(high.alias("a"), low.alias("b")).distinct(), "edges")
    before = state(edges)
    while before[0]:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        grown = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        grown = settle(grown, "large-star")
        least = grown.groupBy("a").agg(F.min("b").alias("m"))
        small = grown.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        edges = settle(small.unionByName(least.select("a", F.col("m").alias("b"))).distinct(), "small-star")
        now = state(edges)
        if now == before:
            break
        before = now
    return edges.groupBy("a").agg(F.min("b").alias("component")).withColumnRenamed("a", "node")


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", radius: int = RADIUS, width: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, component_id) of every row. Fingerprints are the nodes, so rows without an id link others like any row."""
    marked = settle(fingerprints(docs, doc_id, text, width), "fingerprints")
    reps = settle(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "representatives")
    known = components(links(reps.select("fp", F.col("fp").alias("rep")), radius))
    # Nodes without edges are their own component.
    named = settle(reps.join(known.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component")), "named")
    first = named.groupBy("component").agg(F.min("least").alias("component_id"))
    return marked.join(named.join(first, "component").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


#: The near-duplicate stage: words of a shingle; least share of common shingles, as a fraction.
STAGE_WIDTH, ALIKE = 5, (4, 5)
#: Shingles counted together in search of frequent ones, occurrences there that make one frequent, and how many are kept.
COUNT_BLOCK, FREQUENT, FREQUENT_KEPT = 1 << 21, 16, 1 << 16
#: Least slots of a set's sketch; sums of the lesser counts bound the number of common shingles. Larger sets have twice as
#: many for each doubling, so that a slot's count stays small: from about 25 on, any two sets would seem alike.
SLOTS, SLOT_FILL = 256, 8
#: Counts of sketches that are compared at once.
SKETCH_BLOCK = 1 << 22
SLICE = 64
#: Members of a group that a task compares at once; larger groups are dealt over blocks of about that size.
LARGE_GROUP = 1 << 14


def _hashes(text, width: int) -> np.ndarray:
    """All shingle hashes of a text, repeats included."""
    return np.concatenate([np.zeros(0, np.uint64), *(np.array(part, np.uint64) for part in shingle_hashes(text.as_buffer().to_pybytes(), width))])


def _set(hashes: np.ndarray) -> np.ndarray:
    return np.unique(hashes).view(np.int64)


def _sets(texts, width: int) -> list[np.ndarray]:
    """The distinct shingle hashes of some texts, sorted."""
    return [_set(_hashes(x, width)) for x in texts]


def _print(hashes: np.ndarray) -> int:
    """The fingerprint of a text with these shingle hashes, as a signed long."""
    sums = np.zeros(BITS, np.int64)
    for a in range(0, len(hashes), HASH_BLOCK):
        part = hashes[a : a + HASH_BLOCK]
        sums += _bit_sums(part, np.arange(0, len(part), 255)).sum(axis=0, dtype=np.int64)
    return _signed(sum(1 << i for i in np.flatnonzero(2 * sums > len(hashes)).tolist()))


def _slots(n: int) -> int:
    """Slots of a sketch of n shingles: a power of two, so that one sketch folds into half its slots."""
    return max(SLOTS, 1 << (-(-n // SLOT_FILL) - 1).bit_length())


def _sketch(s: np.ndarray) -> bytes:
    slots = _slots(len(s))
    return np.minimum(np.bincount((s.view(np.uint64) % np.uint64(slots)).view(np.int64), minlength=slots), 255).astype(np.uint8).tobytes()


def _keys_of(sets: list[np.ndarray]) -> pa.Array:
    """A hash of each set."""
    from xxhash import xxh64_intdigest

    return pa.array(np.array([xxh64_intdigest(s.tobytes(), SEED) for s in sets], np.uint64).view(np.int64))


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, parts)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*parts, np.zeros(0, np.int64)])))


def _named(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    body = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    return docs.select(F.col(f"`{doc_id}`").cast("long").alias("doc_id"), _text_hash(F.col(f"`{text}`")).alias("text_hash"), body.alias("text"))


def _text_hash(text: Column) -> Column:
    """Tells texts apart; a null text isn't an empty one."""
    return F.xxhash64(text, text.isNull())


def _often(held: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Values met ``FREQUENT`` times or more in all arrays together, and how often. Takes the arrays out of the list.

    Sorted in place: equal values lie together, so such a value equals the one ``FREQUENT - 1`` places on. Nothing
    else as large as the block is made.
    """
    flat = np.concatenate([np.zeros(0, np.int64), *held])
    held.clear()
    flat.sort()
    first = flat[: max(0, len(flat) - FREQUENT + 1)]
    found = np.unique(first[first == flat[len(flat) - len(first) :]])
    return found, np.searchsorted(flat, found, "right") - np.searchsorted(flat, found)


def frequent(rows: DataFrame, width: int = STAGE_WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Some frequent shingles of the texts, sorted, and their counts.

    They only come last in the order of shingles. Any order finds every pair, so a shingle that is
    missed here costs time and no result.
    """

    def run(batches):
        held, n = [], 0

        def out():
            found, counts = _often(held)
            return pa.RecordBatch.from_arrays([pa.array(found), pa.array(counts)], names=["h", "n"])

        for batch in batches:
            for a in range(0, batch.num_rows, SLICE):
                held += _sets(batch.column(0).slice(a, SLICE), width)
                n += sum(map(len, held[-SLICE:]))
                if n >= COUNT_BLOCK:
                    yield out()
                    n = 0
        yield out()

    top = rows.select("text").mapInArrow(run, "h bigint, n bigint").groupBy("h").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "h").limit(FREQUENT_KEPT).collect()
    top.sort()
    return np.array([r["h"] for r in top], np.int64), np.array([r["n"] for r in top], np.int64)


def marked_sets(rows: DataFrame, often: tuple[np.ndarray, np.ndarray], alike: tuple[int, int] = ALIKE, width: int = STAGE_WIDTH) -> DataFrame:
    """(doc_id, text_hash, key, n, sketch, first, fp) of every row: hash and size of the shingle set, counts by hash range,
    first shingles, fingerprint.

    Of a set of n shingles the first ones are n - ceil(alike * n) + 1, rare ones before frequent ones. Two sets
    that are alike enough miss too few of each other's shingles to differ in all of these. Whole sets aren't kept:
    the few that are compared are made from their texts again.
    """
    p, q = alike

    def first(s: np.ndarray) -> np.ndarray:
        known, counts = often
        size = len(s) - -(-p * len(s) // q) + 1 if len(s) else 0
        if len(known) and len(s):
            at = np.minimum(np.searchsorted(known, s), len(known) - 1)
            s = s[np.lexsort((s, np.where(known[at] == s, counts[at], 0)))]
        return s[:size]

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, SLICE):
                ids, hashes, texts = (batch.column(k).slice(a, SLICE) for k in range(3))
                every = [_hashes(x, width) for x in texts]
                sets = [_set(x) for x in every]
                sketches = pa.array([_sketch(s) for s in sets], pa.binary())
                sizes = pa.array([len(s) for s in sets], pa.int32())
                yield pa.RecordBatch.from_arrays([ids, hashes, _keys_of(sets), sizes, sketches, _lists([first(s) for s in sets]), pa.array([_print(x) for x in every], pa.int64())], names=["doc_id", "text_hash", "key", "n", "sketch", "first", "fp"])

    return rows.mapInArrow(run, "doc_id bigint, text_hash bigint, key bigint, n int, sketch binary, first array<bigint>, fp bigint")


def whole_sets(rows: DataFrame, width: int = STAGE_WIDTH) -> DataFrame:
    """(key, tokens) of some texts."""

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, SLICE):
                sets = _sets(batch.column(0).slice(a, SLICE), width)
                yield pa.RecordBatch.from_arrays([_keys_of(sets), _lists(sets)], names=["key", "tokens"])

    return rows.select("text").mapInArrow(run, "key bigint, tokens array<bigint>")


class _Postings:
    """The members that hold each shingle, for some of the sets of a group."""

    def __init__(self, sets: list[np.ndarray], members: np.ndarray):
        flat = np.concatenate([sets[i] for i in members.tolist()])
        order = np.argsort(flat, kind="stable")
        self.owner = np.repeat(members.astype(np.int32), [len(sets[i]) for i in members.tolist()])[order]
        flat = flat[order]
        first = np.flatnonzero(np.diff(flat, prepend=flat[:1] - 1)) if len(flat) else np.zeros(0, np.int64)
        self.tokens, self.ptr = flat[first], np.append(first, len(flat))

    def common(self, s: np.ndarray, n: int) -> np.ndarray:
        """How many shingles of ``s`` each of n members holds. Members share few, unless they are copies."""
        out = np.zeros(n, np.int64)
        if not len(self.tokens):
            return out
        at = np.searchsorted(self.tokens, s)
        at = at[self.tokens[np.minimum(at, len(self.tokens) - 1)] == s]
        lengths = self.ptr[at + 1] - self.ptr[at]
        ends = np.cumsum(lengths)
        cuts = np.searchsorted(ends, np.arange(SKETCH_BLOCK, ends[-1] if len(ends) else 0, SKETCH_BLOCK))
        for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(at)], strict=True):  # some postings at a time
            if b > a:
                m = lengths[a:b]
                places = np.arange(m.sum()) + np.repeat(self.ptr[at[a:b]] - (np.cumsum(m) - m), m)
                out += np.bincount(self.owner[places], minlength=n)
        return out


def _set_forest(keys: list[int], sets: list[np.ndarray], alike: tuple[int, int]) -> list[tuple[int, int]]:
    """Edges of the components of sets that are alike enough, by exact counts of common shingles: from a first member to each other."""
    p, q = alike
    sizes = np.array([len(s) for s in sets])
    left, edges, queue, root = np.arange(1, len(sets)), [], [0], 0
    index, held = None, 0
    while queue and len(left):
        x = queue.pop()
        if index is None or 2 * len(left) < held:  # members that are placed leave the postings
            index, held = _Postings(sets, left), len(left)
        common = index.common(sets[x], len(sets))[left]
        hit = (q * common >= p * (sizes[left] + sizes[x] - common)) & (q * sizes[left] >= p * sizes[x]) & (q * sizes[x] >= p * sizes[left])
        near = left[hit]
        edges += [(keys[root], keys[y]) for y in near.tolist()]
        left = left[~hit]
        queue += near.tolist()
        if not queue and len(left):
            root = int(left[-1])
            queue.append(root)
            left = left[:-1]
    return edges


class _Sketches:
    """Sketches of a group by their slots; those of twice as many are folded in, as sizes of alike sets differ by less."""

    def __init__(self, sketches: list[bytes]):
        self.slots = np.array([len(x) for x in sketches])
        self.row, self.table = {}, {}
        for z in np.unique(self.slots).tolist():
            for held in (z, z // 2):
                if held not in self.table and held >= SLOTS:
                    some = np.flatnonzero((self.slots == held) | (self.slots == 2 * held))
                    self.row[held] = np.full(len(sketches), -1)
                    self.row[held][some] = np.arange(len(some))
                    self.table[held] = np.array([np.frombuffer(sketches[i], np.uint8).astype(np.int16).reshape(-1, held).sum(axis=0) for i in some.tolist()], np.int16)

    def least(self, x: int, others: np.ndarray) -> np.ndarray:
        """Sums of the lesser counts of x and of each of some others, whose slots are as many, half or twice as many."""
        out = np.zeros(len(others), np.int64)
        for z in np.unique(np.minimum(self.slots[others], self.slots[x])).tolist():
            at = np.flatnonzero(np.minimum(self.slots[others], self.slots[x]) == z)
            mine, rows, step = self.table[z][self.row[z][x]], self.row[z][others[at]], max(1, SKETCH_BLOCK // z)
            for a in range(0, len(at), step):
                out[at[a : a + step]] = np.minimum(self.table[z][rows[a : a + step]], mine).sum(axis=1, dtype=np.int64)
        return out


def _possible(keys: list[int], sketches: list[bytes], sizes: list[int], alike: tuple[int, int]) -> list[tuple[int, int]]:
    """Edges of the components of members that may be alike by their sketches, from a first member to each other."""
    p, q = alike
    held, n = _Sketches(sketches), np.array(sizes, np.int64)
    over = n - np.array([np.frombuffer(x, np.uint8).sum(dtype=np.int64) for x in sketches])  # shingles beyond a slot's largest count
    left, found, queue = np.arange(1, len(n)), [[0]], [0]
    while queue and len(left):
        x = queue.pop()
        near = left[(q * n[left] >= p * n[x]) & (q * n[x] >= p * n[left])]
        if len(near):
            most = held.least(x, near) + over[near] + over[x]
            near = near[q * most >= p * (n[near] + n[x] - most)]
            found[-1] += near.tolist()
            left = left[~np.isin(left, near)]
            queue += near.tolist()
        if not queue and len(left):
            queue.append(int(left[-1]))
            found.append([queue[0]])
            left = left[:-1]
    return [(keys[f[0]], keys[i]) for f in found for i in f[1:]]


def _by_group(batches, finish):
    """Rows (h, ...) in the order of h as lists of columns, one call of ``finish`` for each group."""
    now, held = None, []
    for batch in batches:
        for row in zip(*(c.to_pylist() if not pa.types.is_list(c.type) else [c.values[a:b].to_numpy(zero_copy_only=False) for a, b in zip(c.offsets[:-1].to_pylist(), c.offsets[1:].to_pylist(), strict=True)] for c in batch.columns), strict=True):
            if row[0] != now:
                if len(held) > 1:
                    yield from finish([*zip(*held, strict=True)])
                now, held = row[0], []
            held.append(row)
    if len(held) > 1:
        yield from finish([*zip(*held, strict=True)])


def _once(members: DataFrame) -> DataFrame:
    """Rows (h, key) of groups of two or more, with one group of each list of members."""
    prints = [F.bit_xor(F.xxhash64("key", F.lit(k))).alias(f"x{k}") for k in (0, 1)]
    groups = members.groupBy("h").agg(F.count("*").alias("n"), F.min("key").alias("lo"), F.max("key").alias("hi"), *prints).where("n > 1")
    groups = settle(groups.groupBy("n", "lo", "hi", "x0", "x1").agg(F.min("h").alias("h")), "groups")
    two = groups.where("n = 2").select("h", F.explode(F.array("lo", "hi")).alias("key"))
    more = groups.where("n > 2").select("h")
    near = members.where(in_mask(key_mask(more, F.xxhash64("h")), F.xxhash64("h")))
    return settle(two.unionByName(near.join(more, "h", "left_semi").select("h", "key")), "members")


def _compared(rows: DataFrame, find) -> DataFrame:
    """(h, a, b): the edges that ``find`` gives for each group of ``rows`` (h, key, ...); a group comes in the order of its keys."""
    kind = rows.schema["h"].dataType.simpleString()

    def run(batches):
        def finish(group):
            edges = find(*group[1:])
            yield pa.RecordBatch.from_arrays([pa.array([group[0][0]] * len(edges), pa.string() if kind == "string" else pa.int64()), *(pa.array([e[k] for e in edges], pa.int64()) for k in (0, 1))], names=["h", "a", "b"])

        yield from _by_group(batches, finish)

    return rows.repartition("h").sortWithinPartitions("h", "key").mapInArrow(run, f"h {kind}, a bigint, b bigint")


def group_links(members: DataFrame, facts: DataFrame, find, large: int | None = None) -> DataFrame:
    """Edges (a, b) that keep the connectivity of all links within groups of ``members`` (h, key); ``facts`` has a row for each key.

    A group beyond ``large`` members is dealt over blocks, with its first member, the pivot, in each. Members that their
    block connects with the pivot are connected with each other. Only the rest, few among near copies, meet all
    other blocks, again in blocks. So no task holds more than two blocks of a group, and no link between different texts is lost.
    """
    large = large or LARGE_GROUP
    whole = lambda rows: rows.join(facts, "key").select("h", "key", *(c for c in facts.columns if c != "key"))
    blocks = lambda n: F.ceil(F.col(n) / large).cast("int")
    block = lambda n, seed: F.pmod(F.xxhash64("key", F.lit(seed)), F.col(n)).cast("int")
    numbers = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    salt = F.pmod(F.xxhash64("key"), F.lit(SALTS)).cast("int").alias("s")
    spread = lambda df: df.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))).hint("merge")

    hot = settle(members.groupBy("h").agg(F.count("*").alias("n"), F.min("key").alias("pivot")).where(F.col("n") > large).select("h", "pivot", blocks("n").alias("g")), "large-groups")
    if hot.isEmpty():
        return _compared(whole(members), find).select("a", "b")
    hit = in_mask(key_mask(hot, F.xxhash64("h")), F.xxhash64("h"))
    some = members.where(hit)
    small = members.where(~hit).unionByName(some.join(hot.select("h").hint("merge"), "h", "left_anti"))
    placed = settle(some.select("h", "key", salt).join(spread(hot), ["h", "s"]).select("h", "key", "pivot", "g", block("g", 1).alias("i")), "placed")
    pivots = hot.select("h", F.col("pivot").alias("key"), numbers("g").alias("i"))
    unit = F.concat_ws(":", "h", "i")
    first = settle(_compared(whole(placed.select("h", "key", "i").unionByName(pivots).select(unit.alias("h"), "key")), find), "first-blocks")
    reached = first.select(F.col("h").alias("unit"), F.col("a").alias("pivot"), F.col("b").alias("key"))
    rest = settle(placed.where("key <> pivot").withColumn("unit", unit).join(reached.hint("merge"), ["unit", "pivot", "key"], "left_anti").select("h", "key", "g"), "rest")
    counts = rest.groupBy("h").agg(F.count("*").alias("n")).select("h", blocks("n").alias("r"))
    counts = settle(counts, "rest-blocks")
    other = placed.select("h", "key", "i", salt).join(spread(counts), ["h", "s"]).select("h", "key", "i", numbers("r").alias("j"))
    own = rest.select("h", "key", "g", salt).join(spread(counts), ["h", "s"]).select("h", "key", numbers("g").alias("i"), block("r", 2).alias("j"))
    second = _compared(whole(other.unionByName(own).select(F.concat_ws(":", "h", "i", "j").alias("h"), "key")), find)
    return _compared(whole(small), find).select("a", "b").unionByName(first.select("a", "b")).unionByName(second.select("a", "b"))


def possible_links(marked: DataFrame, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """Edges (a, b) between keys of sets that share a first shingle and may be alike by their sketches.

    They keep the connectivity of all alike pairs, and cross few others.
    """
    # One shuffle by shingle serves the distinct members and the groups.
    first = marked.select(each(F.col("first")).alias("h"), "key").where("h is not null").repartition("h").dropDuplicates(["h", "key"])
    members = _once(first)
    wanted = members.select("key").distinct()
    near = marked.select("key", "n", "sketch").where(in_mask(key_mask(wanted, F.xxhash64("key")), F.xxhash64("key")))
    near = near.groupBy("key").agg(F.first("sketch").alias("sketch"), F.first("n").alias("n"))
    return group_links(members, near, lambda keys, sketches, sizes: _possible(keys, sketches, sizes, alike))


def alike_links(rows: DataFrame, marked: DataFrame, alike: tuple[int, int] = ALIKE, width: int = STAGE_WIDTH) -> DataFrame:
    """Edges (a, b) between keys of sets that keep the connectivity of all pairs of sets that are alike enough.

    Sketches part the documents into components that no alike pair crosses, so each set goes to one component
    and is compared there, by exact counts of common shingles.
    """
    known = components(possible_links(marked, alike)).withColumnRenamed("node", "key")
    parts = settle(known.unionByName(known.select(F.col("component").alias("key"), "component").distinct()).distinct(), "parts")
    texts = marked.join(parts.select("key").hint("merge"), "key", "left_semi").groupBy("key").agg(F.min("text_hash").alias("text_hash")).select("text_hash").distinct()
    mask = key_mask(texts, F.col("text_hash"))
    some = rows.where(in_mask(mask, F.col("text_hash")))
    whole = settle(whole_sets(some, width).groupBy("key").agg(F.first("tokens").alias("tokens")).join(parts.select("key").hint("merge"), "key", "left_semi"), "whole-sets")
    return group_links(parts.select(F.col("component").alias("h"), "key"), whole, lambda keys, sets: _set_forest(keys, sets, alike))


def print_links(marked: DataFrame, radius: int) -> DataFrame:
    """Edges (a, b) between keys of sets that keep the connectivity of all fingerprints within the radius."""
    prints = settle(marked.select("fp", "key").distinct(), "prints")
    reps = settle(prints.groupBy("fp").agg(F.min("key").alias("rep")), "print-representatives")
    return prints.join(reps, "fp").where("key <> rep").select(F.col("key").alias("a"), F.col("rep").alias("b")).unionByName(links(reps, radius))


def near_copies(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = STAGE_WIDTH, alike: tuple[int, int] = ALIKE, radius: int | None = None) -> DataFrame:
    """(doc_id, text_hash, component) of every row: rows of equal shingle sets, or alike enough, directly or by others, have one component.

    64-bit fingerprints can't decide this: pairs at 0.8 differ in about 10 bits and often more, where covering
    masks would need thousands of tables. So pairs come from shared first shingles, which miss none. With a
    ``radius``, fingerprints of the same shingles within it link rows too, by covering masks. Components are named by the key of one of their sets, so ids, null or repeated, play no part.
    """
    texts = _named(docs, doc_id, text)
    marked = settle(marked_sets(texts, frequent(texts, width), alike, width), "marked-sets")
    edges = alike_links(texts, marked, alike, width)
    known = components(edges if radius is None else edges.unionByName(print_links(marked, radius)))
    rows = marked.select("doc_id", "text_hash", "key")
    return rows.join(known.withColumnRenamed("node", "key"), "key", "left").select("doc_id", "text_hash", F.coalesce("component", "key").alias("component"))


def op1_simhash_duplicates(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def duplicates_stage(spark, docs: DataFrame, sf_dir: str, radius: int = RADIUS) -> DataFrame:
    """Pipeline stage: one row of each component stays, linked by 5-word fingerprints or by 0.8 of common 5-word shingles.

    It is the row with the smallest id, null ids last, of rows with that id the one with the least hash of its
    text, and of rows equal in both any one. Other texts under its id are judged by their own components.
    """
    rank = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "text_hash")
    found = near_copies(docs, radius=radius).groupBy("component", rank.alias("row")).agg(F.count("*").alias("n"))
    found = settle(found, "near-copies")
    least = found.groupBy("component").agg(F.min("row").alias("least"))
    known = found.join(least, "component").select("row.doc_id", "row.text_hash", (F.col("row") == F.col("least")).alias("stays"), "n")
    # Rows that stay and have no repeats, nearly all, pass without a shuffle; a mask of fixed size tells the others.
    odd = settle(known.where("n > 1 or not stays"), "odd-rows")
    at, own, special, many, row = unused(docs, "text_hash", "id", "special", "many", "row")
    rows = docs.withColumns({at: _text_hash(F.col("text")), own: F.col("doc_id").cast("long")})
    rows = rows.withColumn(special, in_mask(key_mask(odd, F.xxhash64("doc_id", "text_hash")), F.xxhash64(own, at)))
    right = odd.select(F.col("doc_id").alias("o_id"), F.col("text_hash").alias("o_hash"), "n", "stays").hint("merge").alias("o")
    some = rows.where(special).alias("x").join(right, F.col(f"x.{own}").eqNullSafe(F.col("o.o_id")) & (F.col(f"x.{at}") == F.col("o.o_hash")), "left")
    some = some.where("o.n is null or o.stays").select("x.*", F.coalesce("o.n", F.lit(1)).alias(many))
    out = [F.col(f"`{c}`") for c in docs.columns]
    first = Window.partitionBy(own, at).orderBy(F.lit(0))
    twice = some.where(F.col(many) > 1).withColumn(row, F.row_number().over(first)).where(F.col(row) == 1)
    return rows.where(~F.col(special)).select(*out).unionByName(some.where(F.col(many) == 1).select(*out)).unionByName(twice.select(*out))
