"""The near-duplicate stage against all pairs."""

import itertools
import random

import xxhash

from balcut.llm import simhash

from .test_corpus import DOCS, LOWER, clashing, fingerprint, linked


def shingles(t, n=5):
    w = (t or "").translate(LOWER).split()
    return frozenset(" ".join(w[i : i + n]) for i in range(len(w) - n + 1)) or frozenset([" ".join(w)] if w else [])


def groups(texts):
    sets, parent = {i: shingles(t) for i, t in texts.items()}, {i: i for i in texts}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        both, either = len(sets[a] & sets[b]), len(sets[a] | sets[b])
        if 5 * both >= 4 * either:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    return {i: find(i) for i in texts}


def edited():
    r = random.Random(3)
    line, texts = "under the terms of the licence you may copy and share this text as it is", [None, "", " ", "one", "ONE", "two words", "a b c d e", "a b c d e"]
    for _ in range(12):
        words = [f"w{r.randrange(400)}" for _ in range(r.randint(60, 200))] + line.split()
        texts += [" ".join(words), " ".join(words).upper()]
        for edits in (1, 2, 3, 4, 6, 9):
            new = list(words)
            for _ in range(edits):
                new[r.randrange(len(new))] = f"e{r.randrange(10**6)}"
            texts.append(" ".join(new))
    return dict(enumerate(texts))


def test_edited_copies_are_linked(spark, monkeypatch):
    texts = edited()
    want = groups(texts)
    far = [(a, b) for a, b in itertools.combinations(texts, 2) if want[a] == want[b] and (fingerprint(texts[a]) ^ fingerprint(texts[b])).bit_count() > simhash.RADIUS]
    assert far  # op1's radius doesn't reach these
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in texts.items()], DOCS).repartition(3)
    monkeypatch.setattr(simhash, "FREQUENT", 3)  # the order of shingles changes no result
    got = {r["doc_id"]: r["component"] for r in simhash.near_copies(df).collect()}
    assert len(got) == len(want) and len(set(zip(got.values(), (want[i] for i in got), strict=True))) == len(set(want.values())) == len(set(got.values()))


def print_of(t, width=5):
    w = (t or "").translate(LOWER).split()
    hashes = [xxhash.xxh64_intdigest(" ".join(w[i : i + width]).encode(), 42) for i in range(len(w) - width + 1)] or ([xxhash.xxh64_intdigest(" ".join(w).encode(), 42)] if w else [])
    return sum(1 << i for i in range(64) if 2 * sum(h >> i & 1 for h in hashes) > len(hashes))


def both(texts):
    """Components of rows linked by 5-word fingerprints within 3 bits or by 0.8 of common shingles."""
    part = {i: i for i in texts}
    for known in (linked({i: print_of(t) for i, t in texts.items()}), groups(texts)):
        for i, j in known.items():
            old, new = sorted((part[i], part[j]), reverse=True)
            part = {k: new if x == old else x for k, x in part.items()}
    return part


def test_large_groups_are_dealt_over_blocks(spark, monkeypatch):
    texts = edited()
    monkeypatch.setattr(simhash, "LARGE_GROUP", 3)  # nearly all groups are larger
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in texts.items()], DOCS).repartition(3)
    want = groups(texts)
    got = {r["doc_id"]: r["component"] for r in simhash.near_copies(df).collect()}
    assert len(got) == len(want) and len(set(zip(got.values(), (want[i] for i in got), strict=True))) == len(set(want.values())) == len(set(got.values()))


def test_a_chain_keeps_its_links_across_blocks(spark):
    n = 60  # a member links only with its neighbours, so most of a block isn't connected with the pivot
    members = spark.createDataFrame([(h, k) for h in (1, 2) for k in range(n)] + [(3, 5), (3, 90)], "h long, key long")
    facts = spark.createDataFrame([(k, (k * 37) % n if k < n else 6 + (5 * 37) % n) for k in [*range(n), 90]], "key long, at long")

    def find(keys, at):
        part, edges = list(range(len(keys))), []
        for x, y in sorted(itertools.combinations(range(len(keys)), 2)):
            if abs(at[x] - at[y]) <= 1 and part[x] != part[y]:
                old, new = max(part[x], part[y]), min(part[x], part[y])
                part = [new if p == old else p for p in part]
        return [(keys[p], keys[i]) for i, p in enumerate(part) if p != i]

    for large in (7, 10**6):
        edges = simhash.group_links(members, facts, find, large)
        got = {r["node"]: r["component"] for r in simhash.components(edges).collect()}
        assert all(got[k] == 0 for k in range(1, n)) and 90 not in got


def test_the_stage_keeps_one_row_of_each_component(spark):
    texts = edited()
    want = both(texts)
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in texts.items()], DOCS).repartition(3)
    left = simhash.duplicates_stage(spark, clashing(df), "").collect()
    assert sorted(r["doc_id"] for r in left) == sorted(set(want.values())) and all(r["text_hash"] == "x" for r in left)


def test_the_stage_decides_by_row(spark):
    a, b, c = ("alpha beta gamma delta epsilon zeta", "one two three four five six seven", "entirely other words stand in this one")
    rows = [(2, b), (5, b), (5, a), (5, a), (None, c), (None, c), (None, b), (7, None), (8, ""), (3, a)]
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], DOCS).repartition(3)
    out = sorted(((r["doc_id"], r["text"]) for r in simhash.duplicates_stage(spark, df, "").collect()), key=lambda x: (x[0] is None, x[0] or 0))
    assert out == [(2, b), (3, a), (7, None), (None, c)]
    same = [(5, b), (5, a), (2, b)]
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in same], DOCS)
    assert sorted((r["doc_id"], r["text"]) for r in simhash.duplicates_stage(spark, df, "").collect()) == [(2, b), (5, a)]
    assert simhash.duplicates_stage(spark, df.limit(0), "").count() == 0


def test_rows_without_ids_link_others(spark):
    texts = edited()
    rows = [(None if i % 3 == 0 else i, t, "en", "s", 0) for i, t in texts.items()]
    fps = {i: fingerprint(t) for i, t in texts.items()}
    want = linked(fps)
    least = {}
    for i, (d, *_) in enumerate(rows):
        if d is not None:
            least[want[i]] = min(d, least.get(want[i], d))
    got = simhash.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()
    expect = sorted((str(d), least.get(want[i]) if least.get(want[i]) is not None else -1) for i, (d, *_) in enumerate(rows))
    assert sorted((str(r["doc_id"]), -1 if r["component_id"] is None else r["component_id"]) for r in got) == expect


def test_long_texts_that_share_a_line_are_not_compared():
    """counts in few slots made all long sets of a group seem alike, and every pair of them was compared."""
    import numpy as np

    r = np.random.default_rng(5)
    base = [np.unique(r.integers(-(2**63), 2**63, n)) for n in (1800, 2048, 2050, 4000, 4200, 8000, 8300, 9000) for _ in range(4)]
    sets = [np.unique(np.append(s, 7)) for s in base]
    for i, share in ((0, 0.9), (7, 0.95), (12, 0.86), (20, 0.97)):  # alike across a doubling of slots too
        keep = sets[i][: int(share * len(sets[i]))]
        sets.append(np.unique(np.append(keep, [7, *r.integers(-(2**63), 2**63, len(sets[i]) // 50)])))
    keys, sizes = list(range(len(sets))), [len(s) for s in sets]
    want = {(i, j) for i, j in itertools.combinations(keys, 2) if 5 * len(np.intersect1d(sets[i], sets[j])) >= 4 * len(np.union1d(sets[i], sets[j]))}
    assert len(want) == 4
    for edges in (simhash._possible(keys, [simhash._sketch(s) for s in sets], sizes, (4, 5)), simhash._set_forest(keys, sets, (4, 5))):
        assert {tuple(sorted(e)) for e in edges} == want
