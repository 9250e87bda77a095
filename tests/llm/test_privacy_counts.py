"""Disclosure counts of personal data against plain counts, and texts cut at their spans."""

import math
import random
import re
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from balcut.llm import privacy, shared

from .test_corpus import CLASH, DOCS, clashing, private


def corpus():
    r = random.Random(5)
    long = "q" * 90
    mails = ["ann@a.example", "bob@b.example", "+49 1234 567890"]
    out = []
    for _ in range(80):
        words = [r.choice(["alpha", "Beta,", "(gamma)", "delta", "***", "omega--", long, "epsilon!?"]) for _ in range(r.randint(3, 25))]
        if r.random() < 0.6:
            at, k = r.randrange(len(words)), r.randrange(3)
            words[at:at] = [mails[k], f"Signed{k},"] if r.random() < 0.8 else [mails[k]]
        out.append(" ".join(words))
    return out + [None, "", out[0], out[0]]


def plain(texts, support=3):
    """(n, n_e, n_t, n_et) by hand; distinct texts count once."""
    bare = lambda w: re.sub(r"^[^\w]+|[^\w]+$", "", w.lower())
    n_e, n_t, n_et = Counter(), Counter(), Counter()
    distinct = {t or "" for t in texts}
    for t in distinct:
        base = private(t)
        n_t.update({bare(m[0]) for m in re.finditer(r"\S+", t)})
        n_e.update({(k, t[a:b]) for a, b, k in base})
        near = set()
        for a, b, k in base:
            for m in re.finditer(r"\S+", t):
                if m.start() < b + privacy.REACH and a < m.end() + privacy.REACH and not any(m.start() < y and x < m.end() for x, y, _ in base) and len(bare(m[0])) >= privacy.MIN_TERM:
                    near.add(((k, t[a:b]), bare(m[0])))
        n_et.update(near)
    return len(distinct), n_e, n_t, {p: n for p, n in n_et.items() if n >= support}


def test_counts_and_disclosure(spark):
    texts = corpus()
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], DOCS).repartition(4)
    scanned = shared.settle(privacy.scan_texts(clashing(docs), "doc_id", "text"), "privacy-test")
    n, n_e, n_t, n_et = plain(texts)
    key = {r["e"]: k for k in n_e for r in [spark.range(1).select(F.xxhash64(F.lit(k[0]), F.lit(k[1])).alias("e")).first()]}
    got = {(key[r["entity"]], r["term"]): (r["n_et"], r["n_e"], r["n_t"]) for r in privacy.counts_of(clashing(docs), scanned).collect()}
    assert got == {(e, t): (c, n_e[e], n_t[t]) for (e, t), c in n_et.items()} and any(len(t) == 90 for _, t in got)
    told = {(key[r["entity"]], r["term"]): r["disclosure"] for r in privacy.disclosure(docs, scanned).collect()}
    for (e, t), c in n_et.items():
        assert abs(told[e, t] - math.log(n * c / (n_e[e] * n_t[t])) / math.log(n / n_e[e])) < 1e-8


@pytest.mark.parametrize("hot", [1, 10_000])
def test_added_spans(spark, monkeypatch, hot):
    """The added spans are those of the terms over the thresholds, whether pairs count as hot or not."""
    monkeypatch.setattr(privacy, "HOT", hot)
    texts = corpus()
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], DOCS)
    n, n_e, n_t, n_et = plain(texts)
    worth = {p: math.log(n * c / (n_e[p[0]] * n_t[p[1]])) / math.log(n / n_e[p[0]]) for p, c in n_et.items()}
    want = defaultdict(set)
    for i, t in enumerate(texts):
        base = private(t or "")
        for a, b, k in base:
            for m in re.finditer(r"\S+", t):
                w = re.sub(r"^[^\w]+|[^\w]+$", "", m[0].lower())
                x = worth.get(((k, t[a:b]), w), 0)
                if x >= 0.2 and m.start() < b + privacy.REACH and a < m.end() + privacy.REACH and not any(m.start() < y and q < m.end() for q, y, _ in base):
                    want[i].add((m.start(), m.end()))
    got = {r["doc_id"]: {(s["start"], s["end"]) for s in r["added"]} for r in privacy.sanitise_spans(docs, generalise=0.2, remove=0.4).collect()}
    assert len(got) == len(texts) and all(got[i] == want[i] for i in got) and any(want.values())


def test_clashing_columns_stay(spark):
    docs = clashing(spark.createDataFrame([(1, "mail a@b.example now", "en", "s", 0), (None, "mail c@d.example", "en", "s", 0), (2, None, "en", "s", 0)], DOCS))
    out = privacy.sanitised(docs, privacy.sanitise_spans(docs)).collect()
    assert sorted(r["text"] or "" for r in out) == ["", "mail [EMAIL]", "mail [EMAIL] now"] and all(r[c] == "x" for r in out for c in CLASH)


@pytest.mark.parametrize("block", [3, 4096])
def test_cut_out(spark, monkeypatch, block):
    monkeypatch.setattr(shared, "CUT_BLOCK", block)
    r = random.Random(1)
    rows = []
    for _ in range(40):
        text = "".join(r.choice("abé😀\n") for _ in range(r.randint(1, 40)))
        at = sorted(r.sample(range(len(text) + 1), 2 * r.randint(0, min(3, len(text) // 2))))
        rows.append((text, [(a, b, "#") for a, b in zip(at[::2], at[1::2], strict=True)]))
    df = spark.createDataFrame(rows, "text string, spans array<struct<start:int,end:int,label:string>>")
    for row in df.withColumn("got", shared.cut_out(F.col("text"), F.col("spans"))).collect():
        want, last = "", 0
        for s in row["spans"]:
            want, last = want + row["text"][last : s["start"]] + "#", s["end"]
        assert row["got"] == want + row["text"][last:]
