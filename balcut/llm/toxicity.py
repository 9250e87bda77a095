"""Toxicity: gradient-boosted trees over dense text features, with isotonic calibration.

Features are densities of a fixed and a learnt lexicon, nearness of their words to the second
person, capitals, punctuation and obfuscation rates. The learnt lexicon weighs words and word
beginnings by their log odds in labelled texts. Labels serve only in rows whose fold isn't the held-out
one: two folds make the lexicon, one the trees, one the calibration, so no stage sees what an earlier one fitted.
Fitting takes a bounded sample of labelled rows (``FIT_ROWS`` to a fold); scoring takes every row.

Defined results: a null or empty text has zero features and a score like any other; repeated labels of
a document count once, the higher one, and of repeated documents of one id one text is learnt from; documents without a label are scored all the same; without
labels, or with one class only, every score is the share of that class; an empty table gives an empty
result; texts of any length are read whole; further columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import settle, table

#: A small public list of insults (fixed values); the learnt lexicon adds what the labels show.
INSULTS = frozenset("idiot idiots moron morons stupid loser losers scum trash pathetic worthless disgusting clown clowns dumb fool fools liar hate ugly garbage filth jerk creep vermin".split())
#: Second person pronouns of four languages (fixed values).
SECOND_PERSON = frozenset("you your yours yourself du dich dir dein deine ihr euch tu toi te ton ta tes vous votre vos tú ti tus usted ustedes vosotros".split())
FOLDS, HELD_OUT = 5, 0
LEXICON_FOLDS, TREE_FOLD, CALIBRATION_FOLD = (1, 2), 3, 4
#: Labelled rows to a fold at most, on average; entries of the learnt lexicon; least texts with an entry; its least log odds.
FIT_ROWS, LEXICON_SIZE, LEXICON_TEXTS, LEXICON_ODDS = 8_000, 8_000, 4, 1.5
#: Lengths of the word beginnings in the lexicon.
BEGINNINGS = (4, 5, 6, 7, 8)
TREES, DEPTH, RATE, BINS, LEAF = 80, 3, 0.15, 32, 5.0
NEAR = 3
CACHE_WORDS, BLOCK_CHARS = 300_000, 1 << 20
_STRIP = ".,;:!?\"'()[]{}<>|&%$#*…«»„“”-"
FEATURES = ("words", "insults", "insult share", "learnt sum", "learnt share", "learnt highest", "learnt second", "near second person", "second person", "capitals", "capital words", "exclamation", "punctuation", "marks in words", "digits in words", "long runs", "variety")


def held_out(doc_id: Column) -> Column:
    return fold(doc_id) == HELD_OUT


def fold(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo the number of folds."""
    return (F.crc32(doc_id.cast("string")) % FOLDS).cast("int")


def stems(word: str) -> set[str]:
    return {word, *(word[:k] + "*" for k in BEGINNINGS if len(word) >= k)}


_SPACE = re.compile(r"\s").search


def _blocks(text: str):
    """A text's words, in blocks that end at white space, so that texts of any length take bounded memory."""
    a = 0
    while a < len(text):
        cut = _SPACE(text, min(len(text), a + BLOCK_CHARS))
        b = cut.start() if cut else len(text)
        yield text[a:b].split()
        a = b


class Reader:
    """Turns texts into feature vectors; keeps what it found about frequent words."""

    def __init__(self, lexicon: dict[str, float]):
        self.lexicon, self.known = lexicon, {}
        self.run = re.compile(r"(\w)\1\1").search
        self.inner = re.compile(r"\w[^\w\s'’.-]+\w").search

    def word(self, raw: str) -> tuple:
        """(bare word, insult, learnt weight, second person, capitals, mark inside, digit inside, long run)."""
        bare = raw.strip(_STRIP)
        low = bare.lower()
        weight = max((self.lexicon.get(s, 0.0) for s in stems(low)), default=0.0) if low else 0.0
        letters = any(c.isalpha() for c in bare)
        found = (low in INSULTS, weight, low in SECOND_PERSON, len(bare) > 2 and bare.isupper(), bool(self.inner(bare)) and letters, letters and any(c.isdigit() for c in bare), bool(self.run(bare)))
        if len(self.known) >= CACHE_WORDS:
            self.known.clear()
        self.known[raw] = found
        return found

    def features(self, text: str) -> list[float]:
        n = insults = second = shouted = inner = digits = runs = near = learnt = 0
        total, high, next_high, last_you, last_bad = 0.0, 0.0, 0.0, -99, -99
        kinds: set[str] = set()
        get, look = self.known.get, self.word
        for words in _blocks(text):
            for raw, times in Counter(words).items():
                found = get(raw) or look(raw)
                if found[0]:
                    insults += times
                w = found[1]
                if w:
                    learnt += times
                    total += w * times
                    if w > high:
                        high, next_high = w, high
                    elif w > next_high:
                        next_high = w
                if found[2]:
                    second += times
                if found[3]:
                    shouted += times
                if found[4]:
                    inner += times
                if found[5]:
                    digits += times
                if found[6]:
                    runs += times
            kinds.update(words)
            if (insults or learnt) and second:
                for i, raw in enumerate(words, n):
                    found = get(raw) or look(raw)
                    if found[2]:
                        last_you = i
                        near += i - last_bad <= NEAR
                    elif found[0] or found[1]:
                        last_bad = i
                        near += i - last_you <= NEAR
            n += len(words)
        data = np.frombuffer(text.encode(), np.uint8)
        of = np.bincount(data, minlength=256) if len(data) else np.zeros(256, np.int64)
        chars, per = max(1, len(data)), max(1, n)
        marks = int(of[33:48].sum() + of[58:65].sum() + of[91:97].sum() + of[123:127].sum())
        return [
            np.log1p(n), np.log1p(insults), insults / per, np.log1p(total), learnt / per, high, next_high, near / per, second / per,
            int(of[65:91].sum()) / chars, shouted / per, int(of[33] + of[63]) / per, marks / chars, inner / per, digits / per, runs / per, len(kinds) / per,
        ]


@dataclass
class Model:
    """Boosted trees as arrays, the calibration's steps, and the lexicon they read with."""

    lexicon: dict[str, float]
    edges: np.ndarray
    start: float
    feature: np.ndarray
    cut: np.ndarray
    leaf: np.ndarray
    knots: np.ndarray
    values: np.ndarray

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        for f, c, leaf in zip(self.feature, self.cut, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(DEPTH):
                node = 2 * node + 1 + (x[np.arange(len(x)), f[node]] > c[node])
            out += leaf[node - (2**DEPTH - 1)]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        if not len(self.knots):
            return np.full(len(x), self.start)
        return np.round(np.clip(np.interp(self.raw(x), self.knots, self.values), 0, 1), 6)


def boosted(x: np.ndarray, y: np.ndarray, trees: int = TREES) -> tuple[np.ndarray, float, np.ndarray, np.ndarray, np.ndarray]:
    """Boosting on the logistic loss with histogram splits and Newton leaves."""
    n, width = x.shape
    edges = np.array([np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1]) for k in range(width)])
    binned = np.array([np.searchsorted(edges[k], x[:, k], "left") for k in range(width)])
    start = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    raw = np.full(n, start)
    inner, leaves = 2**DEPTH - 1, 2**DEPTH
    features, cuts, values = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = y - p, p * (1 - p)
        node = np.zeros(n, np.int64)
        f, c = np.zeros(inner, np.int64), np.full(inner, np.inf)
        for depth in range(DEPTH):
            low, many = 2**depth - 1, 2**depth
            gains = np.full((many, width, BINS - 1), -np.inf)
            for k in range(width):
                at = (node - low) * BINS + binned[k]
                gs = np.bincount(at, g, many * BINS).reshape(many, BINS).cumsum(1)
                hs = np.bincount(at, h, many * BINS).reshape(many, BINS).cumsum(1)
                gl, hl, ga, ha = gs[:, :-1], hs[:, :-1], gs[:, -1:], hs[:, -1:]
                gain = gl**2 / (hl + 1) + (ga - gl) ** 2 / (ha - hl + 1) - ga**2 / (ha + 1)
                gains[:, k] = np.where((hl > LEAF / 10) & (ha - hl > LEAF / 10), gain, -np.inf)
            flat = gains.reshape(many, -1)
            pick = flat.argmax(1)
            for j in range(many):
                if flat[j, pick[j]] > 1e-9:
                    f[low + j], c[low + j] = pick[j] // (BINS - 1), edges[pick[j] // (BINS - 1), pick[j] % (BINS - 1)]
            node = 2 * node + 1 + (x[np.arange(n), f[node]] > c[node])
        at = node - inner
        value = RATE * np.bincount(at, g, leaves) / (np.bincount(at, h, leaves) + 1)
        raw += value[at]
        features.append(f), cuts.append(c), values.append(value)
    return edges, start, np.array(features), np.array(cuts), np.array(values)


def isotonic(raw: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled neighbours until the means rise: centres and smoothed means of the pools."""
    order = np.lexsort((y, raw))
    pools: list[list[float]] = []
    for r, t in zip(raw[order].tolist(), y[order].tolist(), strict=True):
        pools.append([t, 1.0, r, r])
        while len(pools) > 1 and pools[-2][0] / pools[-2][1] >= pools[-1][0] / pools[-1][1]:
            s, n, _, high = pools.pop()
            pools[-1] = [pools[-1][0] + s, pools[-1][1] + n, pools[-1][2], high]
    knots = np.array([x for p in pools for x in (p[2], p[3])])
    means = np.array([(p[0] + 0.5 * (k / max(1, len(pools) - 1))) / (p[1] + 0.5) for k, p in enumerate(pools) for _ in range(2)])
    return knots, np.maximum.accumulate(means)


def learnt_lexicon(sample: DataFrame) -> dict[str, float]:
    """Log odds of words and beginnings between toxic and other texts; each text counts an entry once."""

    def run(batches):
        for batch in batches:
            seen: dict[str, list[int]] = {}
            for text, toxic in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                words = {w.strip(_STRIP).lower() for part in _blocks(text.as_py()) for w in part}
                for s in set().union(*map(stems, words)) if words else ():
                    seen.setdefault(s, [0, 0])[toxic] += 1
            yield pa.RecordBatch.from_arrays([pa.array(list(seen)), pa.array([v[0] for v in seen.values()], pa.int64()), pa.array([v[1] for v in seen.values()], pa.int64())], names=["entry", "clean", "toxic"])

    sizes = {r["toxic"]: r["count"] for r in sample.groupBy("toxic").count().collect()}
    if not sizes.get(1) or not sizes.get(0):
        return {}
    counts = sample.select("text", "toxic").mapInArrow(run, "entry string, clean bigint, toxic bigint").groupBy("entry").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    odds = F.log((F.col("toxic") + 0.1) / (sizes[1] + 0.2)) - F.log((F.col("clean") + 0.5) / (sizes[0] + 1.0))
    least = min(LEXICON_TEXTS, max(2, sizes[1] // 8))
    best = counts.where(F.col("toxic") >= least).withColumn("odds", F.round(odds, 6)).where(F.col("odds") >= LEXICON_ODDS)
    # Entries by the evidence they carry; the list is bounded and goes along with the model.
    return {r["entry"]: r["odds"] for r in best.orderBy(F.desc(F.col("odds") * F.sqrt("toxic")), "entry").limit(LEXICON_SIZE).collect()}


def labelled_sample(docs: DataFrame, labels: DataFrame, doc_id: str, text: str, rows: int = FIT_ROWS) -> DataFrame:
    """(fold, toxic, text) of a bounded sample of labelled rows outside the held-out fold.

    Ids are chosen by their hash under a threshold set by the fold's size, so the sample needs no
    sort, is the same in every run, and is small enough to broadcast at any size of the tables.
    """
    known = labels.where("toxic is not null").groupBy(F.col(doc_id).alias("_id")).agg(F.max("toxic").alias("toxic")).withColumn("fold", fold(F.col("_id"))).where(F.col("fold") != HELD_OUT)
    known = known.withColumn("part", F.when(F.col("fold").isin(*LEXICON_FOLDS), F.lit(LEXICON_FOLDS[0])).otherwise(F.col("fold")))
    sizes = {r["part"]: r["count"] for r in known.groupBy("part").count().collect()}
    span = 1 << 20
    below = F.lit(span)
    for part, n in sizes.items():
        below = F.when(F.col("part") == part, F.lit(span if n <= rows else int(span * rows / n))).otherwise(below)
    chosen = known.where(F.pmod(F.xxhash64("_id"), F.lit(span)) < below).select("_id", "part", F.col("toxic").cast("int").alias("toxic"))
    rows = docs.select(F.col(doc_id).alias("_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(F.broadcast(chosen), "_id")
    # Repeated documents of an id count once, so the sample stays as large as the labels allow.
    return rows.groupBy("_id").agg(F.first("part").alias("part"), F.first("toxic").alias("toxic"), F.min("text").alias("text")).select("part", "toxic", "text")


def _vectors(df: DataFrame, lexicon: dict[str, float]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of a bounded sample: numbers only reach the driver."""
    shared = df.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches):
        reader = Reader(shared.value)
        for batch in batches:
            rows = [reader.features(t.as_py()) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, pa.list_(pa.float64()))], names=["part", "toxic", "x"])

    got = df.mapInArrow(run, "part int, toxic int, x array<double>").toArrow()
    x = np.array(got["x"].to_pylist(), float).reshape(-1, len(FEATURES))
    order = np.lexsort(x.T)  # the order of rows must not depend on the order of tasks
    return got["part"].to_numpy()[order], got["toxic"].to_numpy()[order].astype(float), x[order]


def fit(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", rows: int = FIT_ROWS) -> Model:
    sample = settle(labelled_sample(docs, labels, doc_id, text, rows), "labelled")
    lexicon = learnt_lexicon(sample.where(F.col("part") == LEXICON_FOLDS[0]))
    part, y, x = _vectors(sample.where(F.col("part") != LEXICON_FOLDS[0]), lexicon)
    train, check = part == TREE_FOLD, part == CALIBRATION_FOLD
    share = float(y.mean()) if len(y) else 0.0
    empty = np.empty(0)
    if not train.any() or len(set(y[train])) < 2:
        return Model(lexicon, empty, share, empty, empty, empty, empty, empty)
    edges, start, feature, cut, leaf = boosted(x[train], y[train])
    model = Model(lexicon, edges, start, feature, cut, leaf, np.zeros(1), np.zeros(1))
    both = check if check.any() and len(set(y[check])) == 2 else train
    model.knots, model.values = isotonic(model.raw(x[both]), y[both])
    return model


def score(docs: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, score) of every row; only the text enters the score."""
    kind = docs.schema[doc_id].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        reader = Reader(shared.value.lexicon)
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                ids, texts = batch.column(0).slice(a, 512), batch.column(1).slice(a, 512)
                x = np.array([reader.features(t.as_py()) for t in texts], float).reshape(-1, len(FEATURES))
                yield pa.RecordBatch.from_arrays([ids, pa.array(shared.value.score(x))], names=["doc_id", "score"])

    return docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(run, f"doc_id {kind}, score double")


def op6_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
