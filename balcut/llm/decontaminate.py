"""Benchmark decontamination: q-gram lemma filtering in overlapping diagonal bands, then banded alignment.

Texts are lower-cased, white space runs become one blank, and edits are counted on UTF-8 bytes. Every
benchmark item is cut into overlapping passages. If a document holds a passage of m bytes with at most
k edits, both share at least m + 1 - q (k + 1) q-grams, and these lie on k + 1 neighbouring diagonals.
So shared q-grams are counted per passage in bands of diagonals that overlap by k; bands under the
passage's threshold can't hold a match and go, the others are aligned within their diagonals.

The benchmark is read in blocks of a checked size; each block's q-gram index goes to the executors
and the documents stream past it without a shuffle.

Defined results: null and empty texts, and items that are null or blank, match nothing; an item under ``MIN_CHARS``
bytes has no q-grams to spare and matches documents that are equal to it; items without an id match like others,
with a null id; repeated items of one id count as one, repeated documents are judged one by one; empty tables give
an empty result; other columns than the named ones are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import table

Q = 10
#: Passage length, step between passages, and edits allowed: one in so many bytes.
PASSAGE, STEP, EDIT_RATE = 96, 48, 12
MIN_CHARS = 24
#: Diagonals to a band besides the overlap.
BAND = 16
#: Zero bytes between documents; more than any edit budget.
GAP = 32
#: Bits of the hit table; bytes of documents looked at together; bytes of benchmark text to a block.
TABLE_BITS, CHUNK, BLOCK_BYTES = 20, 1 << 22, 8 << 20
#: Shared q-grams that are looked at together; passages with a common q-gram are taken in turns beyond it.
HITS = 1 << 22
_MIX, _MIX2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
MATCH = "item_id bigint, passages int, edits int"


def normalised(text: str) -> bytes:
    return " ".join(text.lower().split()).encode()


def budget(m: int) -> int:
    """Edits allowed in a passage of m bytes: as many as leave some q-grams to count."""
    return max(0, min(m // EDIT_RATE, (m + 1 - 4) // Q - 1))


def grams(text: bytes | memoryview) -> np.ndarray:
    """A number for each q-gram, mixed from its first and last eight bytes; read in place."""
    n = len(text) - Q + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    eight = np.ndarray((len(text) - 7,), "<u8", buffer=text, strides=(1,))
    return eight[:n] * _MIX ^ eight[Q - 8 : Q - 8 + n] * _MIX2


def _slot(g: np.ndarray) -> np.ndarray:
    return (g * _MIX >> np.uint64(64 - TABLE_BITS)).astype(np.int64)


@dataclass
class Index:
    """Passages of one block of items and the places of their q-grams."""

    items: list[int | None]
    short: dict[bytes, list[int | None]]
    passages: list[bytes]
    need: np.ndarray
    edits: np.ndarray
    keys: np.ndarray
    first: np.ndarray
    segment: np.ndarray
    offset: np.ndarray
    seen: np.ndarray

    @classmethod
    def of(cls, items: list[tuple[int | None, str | None]]) -> Index:
        ids, passages, short = [], [], {}
        for item, text in items:
            body = normalised(text or "")
            if len(body) < MIN_CHARS:
                if body and item not in short.setdefault(body, []):
                    short[body].append(item)
                continue
            starts = range(0, max(1, len(body) - PASSAGE + STEP), STEP) if len(body) > PASSAGE else [0]
            for a in dict.fromkeys(min(a, max(0, len(body) - PASSAGE)) for a in starts):
                ids.append(item)
                passages.append(body[a : a + PASSAGE])
        lists = [grams(p) for p in passages]
        sizes = np.array([len(x) for x in lists], np.int64)
        flat = np.concatenate(lists) if lists else np.empty(0, np.uint64)
        order = np.argsort(flat, kind="stable")
        keys, first = np.unique(flat[order], return_index=True)
        seen = np.zeros(1 << TABLE_BITS, bool)
        seen[_slot(keys)] = True
        edits = np.array([budget(len(p)) for p in passages], np.int64)
        need = np.array([len(p) for p in passages], np.int64) + 1 - Q * (edits + 1)
        segment = np.repeat(np.arange(len(passages)), sizes)
        offset = np.concatenate([np.arange(n) for n in sizes.tolist()]) if lists else np.empty(0, np.int64)
        return cls(ids, short, passages, need, edits, keys, np.append(first, len(flat)), segment[order], offset[order], seen)

    def hits(self, text: bytes):
        """(diagonal, passage) of every q-gram that the text shares with a passage, ``HITS`` or a few more at once."""
        for a in range(0, max(0, len(text) - Q + 1), 1 << 18):
            g = grams(memoryview(text)[a : a + (1 << 18) + Q - 1])
            place = np.flatnonzero(self.seen[_slot(g)])
            if not len(place) or not len(self.keys):
                continue
            at = np.searchsorted(self.keys, g[place])
            at[at == len(self.keys)] = 0
            true = self.keys[at] == g[place]
            place, at = place[true] + a, at[true]
            first, many = self.first[at], self.first[at + 1] - self.first[at]
            while len(place):
                # Some q-grams have very many passages: each turn takes a slice of what is left of every one.
                some = np.minimum(many, max(1, HITS // len(place)))
                row = np.repeat(first - np.cumsum(some) + some, some) + np.arange(some.sum())
                yield np.repeat(place, some) - self.offset[row], self.segment[row]
                left = many > some
                place, first, many = place[left], (first + some)[left], (many - some)[left]

    def bands(self, text: bytes) -> tuple[np.ndarray, np.ndarray]:
        """(first diagonal, passage) of the bands that hold enough shared q-grams."""
        width = (len(text) + 2 * PASSAGE) // BAND + 6
        held: list[tuple[np.ndarray, np.ndarray]] = []
        rows = 0

        def summed() -> tuple[np.ndarray, np.ndarray]:
            key, place = np.unique(np.concatenate([k for k, _ in held]), return_inverse=True)
            return key, np.bincount(place, np.concatenate([n for _, n in held])).astype(np.int64)

        for diagonal, passage in self.hits(text):
            band = diagonal // BAND
            over = diagonal - band * BAND < self.edits[passage]
            band, passage = np.concatenate((band, band[over] - 1)), np.concatenate((passage, passage[over]))
            held.append(np.unique(passage * width + (band + PASSAGE // BAND + 2), return_counts=True))
            rows += len(held[-1][0])
            if rows > 4 * HITS:
                held = [summed()]
                rows = 0
        if not held:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        key, n = summed()
        passage, band = key // width, key % width - PASSAGE // BAND - 2
        enough = n >= self.need[passage]
        return band[enough] * BAND, passage[enough]

    def aligned(self, text: bytes) -> list[tuple[int, int, int]]:
        """(place, passage, edits) of every passage found within its budget."""
        start, passage = self.bands(text)
        found = []
        lengths = np.array([len(p) for p in self.passages], np.int64)
        for m in np.unique(lengths[passage]).tolist():
            here = np.flatnonzero(lengths[passage] == m)
            for a in range(0, len(here), 4096):
                some = here[a : a + 4096]
                edits = banded_distance(text, start[some], [self.passages[p] for p in passage[some].tolist()], int(budget(m)))
                good = edits <= self.edits[passage[some]]
                found += zip((start[some][good] + m // 2).tolist(), passage[some][good].tolist(), edits[good].tolist(), strict=True)
        return found


def banded_distance(text: bytes, start: np.ndarray, passages: list[bytes], k: int) -> np.ndarray:
    """For each passage the least edits to a part of the text that starts near ``start``; all of one length.

    One row per passage byte, one column per diagonal of the band; all candidates advance together.
    """
    m, width = len(passages[0]), BAND + 3 * k + 2
    low = start - k
    data = np.frombuffer(text, np.uint8)
    p = np.frombuffer(b"".join(passages), np.uint8).reshape(-1, m)
    steps = np.arange(width)
    row = np.zeros((len(p), width), np.int32)
    for i in range(m):
        at = low[:, None] + i + steps
        inside = (at >= 0) & (at < len(data))
        same = inside & (data[np.where(inside, at, 0)] == p[:, i : i + 1])
        put = row + ~same
        put[:, :-1] = np.minimum(put[:, :-1], row[:, 1:] + 1)
        row = np.minimum.accumulate(put - steps, axis=1) + steps
    return row.min(axis=1)


def matches_in(index: Index, texts: list[str]) -> list[dict[int, tuple[int, int]]]:
    """For each text: item -> (passages found, least edits). Texts are looked at in chunks."""
    out: list[dict[int, tuple[int, int]]] = [{} for _ in texts]
    held, ends, rows, size = [], [], [], 0

    def look():
        nonlocal held, ends, rows, size
        if held:
            found: dict[tuple[int, int], int] = {}
            for place, passage, edits in index.aligned(bytes(GAP) + bytes(GAP).join(held) + bytes(GAP)):
                key = rows[min(int(np.searchsorted(ends, place, "right")), len(rows) - 1)], passage
                found[key] = min(edits, found.get(key, edits))
            for (row, passage), edits in found.items():
                item = index.items[passage]
                n, least = out[row].get(item, (0, edits))
                out[row][item] = (n + 1, min(edits, least))
        held, ends, rows, size = [], [], [], 0

    for i, text in enumerate(texts):
        body = normalised(text)
        if len(body) < MIN_CHARS:
            out[i] |= dict.fromkeys(index.short.get(body, ()), (1, 0))
            continue
        held.append(body)
        rows.append(i)
        size += len(body) + GAP
        ends.append(size + GAP // 2)
        if size >= CHUNK:
            look()
    look()
    return out


def benchmark_blocks(benchmark: DataFrame, item_id: str = "item_id", text: str = "text", block_bytes: int = BLOCK_BYTES) -> Iterator[Index]:
    """Indexes over all items, in blocks of a bounded number of bytes; the driver holds one block at a time."""
    body = benchmark.select(F.col(item_id).cast("bigint").alias("item_id"), F.col(text).alias("text")).where("text is not null")
    total = body.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-int(total) // block_bytes))
    for k in range(n):
        part = body.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k).orderBy("item_id", "text")
        yield Index.of([(r["item_id"], r["text"]) for r in part.toLocalIterator()])


def _in_slices(batch: pa.RecordBatch, column: int):
    """A batch in slices of some rows, with their texts."""
    for a in range(0, batch.num_rows, 512):
        part = batch.slice(a, 512)
        yield part, part.column(column).to_pylist()


def contaminated(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, item_id, passages, edits) of every document and benchmark item with a passage in common."""
    kind = docs.schema[doc_id].dataType.simpleString()
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    found = None
    for index in benchmark_blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            for batch in batches:
                for part, texts in _in_slices(batch, 1):
                    hits = matches_in(shared.value, texts)
                    ids = part.column(0).to_pylist()
                    flat = [(d, item, n, e) for d, of in zip(ids, hits, strict=True) for item, (n, e) in sorted(of.items(), key=lambda x: (x[0] is None, x[0] or 0))]
                    if flat:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*flat, strict=True), (part.column(0).type, pa.int64(), pa.int32(), pa.int32()), strict=True)], names=["doc_id", "item_id", "passages", "edits"])

        part = rows.mapInArrow(run, f"doc_id {kind}, {MATCH}")
        found = part if found is None else found.unionByName(part)
    return found


def clean_documents(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The documents that hold no benchmark passage, decided row by row without a join or shuffle."""
    at = docs.columns.index(text)
    for index in benchmark_blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            for batch in batches:
                for part, texts in _in_slices(batch, at):
                    hits = matches_in(shared.value, [t or "" for t in texts])
                    yield part.filter(pa.array([not h for h in hits]))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op2_benchmark_decontamination(spark, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def decontamination_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents with a benchmark passage go."""
    return clean_documents(docs, table(spark, sf_dir, "benchmark"))
