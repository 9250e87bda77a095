"""What the pipeline's stages leave and hold in a Python worker, which other stages use after them."""

import random
import tracemalloc
import weakref
from collections import Counter

import pyarrow as pa
from balcut.llm import pieces, simhash


class _Task:
    """Stands for a DataFrame; keeps the function that a worker would run."""

    def mapInArrow(self, run, schema):
        self.run = run
        return self

    def collect(self):
        return []

    def __getattr__(self, name):
        return lambda *a, **k: self


def test_a_worker_keeps_no_coder_after_the_pipeline_stage(spark, monkeypatch):
    made = []

    class Seen(pieces.Coder):
        def __init__(self, *args):
            super().__init__(*args)
            made.append(weakref.ref(self))

    monkeypatch.setattr(pieces, "Coder", Seen)
    docs = spark.createDataFrame([(k, f"some words and {k} a$$$ é☃") for k in range(600)] + [(None, None)], "doc_id long, text string")
    rows = docs.toArrow().to_batches(max_chunksize=200)
    rows = [pa.RecordBatch.from_arrays([b.column(0), b.column(1).fill_null("")], names=["doc_id", "text"]) for b in rows]
    want = [pieces.encode(docs, digests=True).orderBy("doc_id").toArrow().to_pylist()]
    monkeypatch.setattr(type(docs), "mapInArrow", lambda self, run, schema: run)
    run = pieces.pieces_stage(spark, docs, "")
    for _ in range(2):  # two tasks of one worker
        got = [r for b in run(iter(rows)) for r in b.to_pylist()]
        want.append(sorted(got, key=lambda r: (r["doc_id"] is not None, r["doc_id"])))
    assert want[0] == want[1] == want[2]
    assert len(made) == 2 and all(r() is None for r in made) and not pieces._CODERS


def test_frequent_shingles_are_counted_in_little_more_than_their_block():
    rng = random.Random(3)
    texts = [" ".join(f"{rng.getrandbits(40):x}" for _ in range(304)) for _ in range(1000)]
    texts += texts[:2] * simhash.FREQUENT + texts[2:4] * (simhash.FREQUENT - 2)
    task = _Task()
    simhash.frequent(task)
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"])
    tracemalloc.start()
    try:
        got = {h: n for b in task.run(iter([batch])) for h, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)}
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    counts = Counter(h for s in simhash._sets(batch.column(0), simhash.STAGE_WIDTH) for h in s.tolist())
    assert got == {h: n for h, n in counts.items() if n >= simhash.FREQUENT} and len(got) == 600
    assert peak < 3 * 8 * sum(counts.values())
