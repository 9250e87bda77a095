"""SentencePiece encoding and decoding with exact n-best segmentation.

A text's pieces form a lattice. A forward Viterbi pass gives for every place the best score from the
start; it is the exact heuristic of a backward A-star search from the end, so hypotheses leave the
search in the order of their whole scores and the first n are the n best segmentations. As every
waiting hypothesis has its exact score, only as many wait as are still wanted.

No piece of the vocabulary spans a line end or goes on after a blank that follows another character
(checked when it is loaded), so a text's lattice falls apart there: words are searched once, kept in a
bounded cache, and the n best of the whole text are combined from the words' own n best. The new words of many
texts take the forward pass together, as arrays; words with characters that are no pieces take it alone. That
pass also keeps how far the second best lies behind: only the n - 1 words with the smallest gap can differ among
the text's n best, so these, and words with ties, are the ones that the backward search goes through.

The model's scores of a byte-pair vocabulary only give an order; scores here are log probabilities
of a Zipf law over that order. Characters without a piece become their UTF-8 bytes.

Defined results: a null text counts as empty and has no pieces; any text, literal piece marks and
long unbroken runs included, decodes to itself; equal scores of a word are ordered by the start and ids of their
last pieces, equal sums of a text by the places of the changed words, last ones first; repeated rows give equal rows; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import ctypes
import gc
import hashlib
import heapq
import math
import re
import struct
import sys
from bisect import insort
from contextlib import suppress
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import table

#: Where the vocabulary lies; a parameter of every entry point.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
N_BEST = 4
#: Offset of the Zipf law; how far a byte's score lies under the least piece's.
ZIPF_SHIFT, BYTE_PENALTY = 2.7, 1.0
#: Words in one of the two generations of a worker's cache, those of searched words, and their greatest length.
CACHE_WORDS, CACHE_SEARCHED, CACHE_CHARS = 300_000, 30_000, 64
#: The same two for the pipeline, whose other stages share the executor's memory.
STAGE_CACHES = 100_000, 12_000
#: Places of the marks that tell a word met before; they are wiped when an eighth of them is set.
CACHE_MARKS = 1 << 22
#: Words that are looked up together.
BLOCK_WORDS = 1 << 16
#: New words that are searched at once; texts and characters whose new words are looked for together.
MET_WORDS, MET_TEXTS, MET_CHARS = 4096, 256, 1 << 21
MARK = "▁"
#: Gap under which two segmentations count as equal; their order is the backward search's.
TIE = 1e-8


@dataclass
class Vocabulary:
    """Pieces with blanks instead of marks, their ids and scores; byte pieces by byte."""

    ids: dict[str, int]
    score: list[float]
    byte: list[int]
    text: list[bytes]
    longest: int
    apart: bool
    begins: set[str]
    ends: set[str]
    #: For each beginning of a piece its score and ids, None where it is no piece itself: one look-up for a forward step.
    steps: dict[str, tuple[float, tuple[int, ...]] | None] = field(init=False)

    def __post_init__(self):
        self.steps = dict.fromkeys(self.begins)
        self.steps |= {p: (self.score[i], (i,)) for p, i in self.ids.items()}

    @classmethod
    def load(cls, model: str = MODEL) -> Vocabulary:
        from sentencepiece import SentencePieceProcessor

        sp = SentencePieceProcessor(model_file=model)
        n = sp.get_piece_size()
        ids, byte, text, rank = {}, [0] * 256, [b""] * n, 0
        score = [0.0] * n
        for i in range(n):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                b = int(piece[3:5], 16)
                byte[b], text[i] = i, bytes([b])
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                plain = piece.replace(MARK, " ")
                ids[plain], text[i] = i, plain.encode()
                score[i] = -math.log(rank + ZIPF_SHIFT)
                rank += 1
        whole = math.log(sum(1 / (r + ZIPF_SHIFT) for r in range(rank)))
        for i in ids.values():
            score[i] -= whole
        low = min((score[i] for i in ids.values()), default=0.0) - BYTE_PENALTY
        for i in byte:
            score[i] = low
        apart = not any("\n" in p or re.search("[^ ] ", p) for p in ids)
        return cls(ids, score, byte, text, max(map(len, ids), default=1), apart, {p[:k] for p in ids for k in range(1, len(p) + 1)}, {p[k:] for p in ids for k in range(len(p))})

    def decode(self, ids) -> str:
        """The text of some ids, without the blank that encoding puts in front."""
        return b"".join(self.text[i] for i in ids).decode()[1:]


def n_best(vocabulary: Vocabulary, word: str, n: int = N_BEST) -> list[tuple[float, tuple[int, ...]]]:
    """The n best segmentations of a word, best first: (score, ids)."""
    known, score, look = vocabulary.ids, vocabulary.score, vocabulary.steps.get
    size = len(word)
    best = [0.0] + [-math.inf] * size
    into: list[list[tuple]] = [[] for _ in range(size + 1)]  # the pieces that end at a place: (start, score, ids)
    spelt: dict[int, tuple[float, tuple[int, ...]]] = {}
    for i in range(size):
        here = best[i]
        if word[i] not in known:
            codes = tuple(vocabulary.byte[b] for b in word[i].encode())
            spelt[i] = sum(score[c] for c in codes), codes
            best[i + 1] = max(best[i + 1], here + spelt[i][0])
        for j in range(i + 1, size + 1):
            step = look(word[i:j], False)
            if step:
                s, codes = step
                into[j].append((i, s, codes))
                if here + s > best[j]:
                    best[j] = here + s
            elif step is False:  # no piece begins like this
                break
    # Backward search: (whole score negated, place, last ids, number, score behind the place, pieces behind as a chain).
    waiting: list[tuple] = [(-round(best[size], 9), size, (), 0, 0.0, None)]
    done: list[tuple[float, tuple[int, ...]]] = []
    made = 0
    while waiting and len(done) < n:
        whole, place, _, _, behind, chain = waiting.pop(0)
        wanted = n - len(done)
        if place == 0:
            ids: list[int] = []
            while chain is not None:
                ids += chain[0]
                chain = chain[1]
            done.append((-whole, tuple(ids)))
            continue
        if place - 1 in spelt:
            s, codes = spelt[place - 1]
            made += 1
            insort(waiting, (-round(best[place - 1] + s + behind, 9), place - 1, codes, made, s + behind, (codes, chain)))
        for start, s, codes in into[place]:
            s += behind
            whole = best[start] + s
            # Clearly worse than all that are still wanted: it would be cut off below.
            if len(waiting) >= wanted and whole < -waiting[wanted - 1][0] - TIE:
                continue
            made += 1
            insort(waiting, (-round(whole, 9), start, codes, made, s, (codes, chain)))
        del waiting[wanted:]
    return done


def two_best(vocabulary: Vocabulary, word: str) -> tuple[tuple[int, ...], float, float]:
    """(ids, score, gap to the second best) of a word: one forward pass that keeps the two best scores of every place.

    The gap tells which words the backward search must look at; where it is 0, the ids are its matter too.
    """
    look, score = vocabulary.steps.get, vocabulary.score
    size = len(word)
    worst = -math.inf
    best, second, by = [worst] * (size + 1), [worst] * (size + 1), [None] * (size + 1)
    best[0] = 0.0
    for i in range(size):
        here, other = best[i], second[i]
        if not look(word[i]):
            codes = tuple(vocabulary.byte[b] for b in word[i].encode())
            cost = sum(score[c] for c in codes)
            a, b, j = here + cost, other + cost, i + 1
            if a > best[j]:
                second[j] = max(best[j], b)
                best[j], by[j] = a, (i, codes)
            elif a > second[j]:
                second[j] = a
        for j in range(i + 1, size + 1):
            step = look(word[i:j], False)
            if step:
                s, codes = step
                a, top = here + s, best[j]
                if a > top:
                    b = other + s
                    second[j] = b if b > top else top
                    best[j], by[j] = a, (i, codes)
                elif a > second[j]:
                    second[j] = a
            elif step is False:  # no piece begins like this
                break
    back: list[tuple[int, ...]] = []
    at = size
    while at:
        at, codes = by[at]
        back.append(codes)
    return tuple(k for codes in reversed(back) for k in codes), best[size], best[size] - second[size]


class Trie:
    """The pieces as sorted arrays of steps, to run ``two_best`` on many words at once."""

    def __init__(self, vocabulary: Vocabulary):
        at = {"": 0} | {p: k for k, p in enumerate(sorted(vocabulary.begins), 1)}
        steps = sorted((at[p[:-1]] << 21 | ord(p[-1]), k) for p, k in at.items() if p)
        self.keys, self.to = (np.array(x, np.int64) for x in zip(*steps, strict=True))
        self.piece = np.full(len(at), -1, np.int32)
        for p, i in vocabulary.ids.items():
            self.piece[at[p]] = i
        self.score = np.array(vocabulary.score)
        self.first = np.full(sys.maxunicode + 1, -1, np.int32)
        ones = self.keys < 1 << 21
        self.first[self.keys[ones]] = self.to[ones]

    def step(self, state: np.ndarray, code: np.ndarray) -> np.ndarray:
        """The states behind a character; -1 where no piece goes on with it."""
        key = state << 21 | code
        k = np.searchsorted(self.keys, key)
        k[k == len(self.keys)] = 0
        return np.where(self.keys[k] == key, self.to[k], -1)

    def two_best(self, words: list[str]) -> list[tuple[bytes, float, float] | None]:
        """(packed ids, score, gap) of each word, as ``two_best`` has them; None for a word with a character that is no piece."""
        size = np.fromiter(map(len, words), np.int64, len(words))
        code = np.frombuffer("".join(words).encode("utf-32-le"), np.uint32).astype(np.int64)
        word = np.repeat(np.arange(len(words)), size)
        start = np.arange(len(code)) - np.repeat(np.cumsum(size) - size, size)
        place = np.arange(len(code))
        spelt = np.zeros(len(words), bool)
        found = []
        for n in range(1, int(size.max()) + 1):
            state = self.step(state, code[place + n - 1]) if n > 1 else self.first[code].astype(np.int64)
            ids = np.where(state >= 0, self.piece[state], -1)
            if n == 1:
                spelt[word[ids < 0]] = True
            hit = place[ids >= 0]
            found.append((hit, np.full(len(hit), n), ids[ids >= 0]))
            on = (state >= 0) & (start[place] + n < size[word[place]])
            place, state = place[on], state[on]
            if not len(place):
                break
        place, length, ids = (np.concatenate(x) for x in zip(*found, strict=True))
        known = ~spelt[word[place]]
        place, length, ids = place[known], length[known], ids[known]
        order = np.argsort(start[place].astype(np.int16), kind="stable")
        place, length, ids = place[order], length[order], ids[order]
        wide = int(size.max()) + 1
        source = word[place] * wide + start[place]
        target, cost = source + length, self.score[ids]
        ends = np.searchsorted(start[place], np.arange(wide))
        best, second = np.full(len(words) * wide, -np.inf), np.full(len(words) * wide, -np.inf)
        by = np.full(len(words) * wide, -1)
        best[::wide] = 0.0
        # All pieces that start at one place of their words end at different places, so they are weighed together.
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            s, t, c = source[a:b], target[a:b], cost[a:b]
            one, top = best[s] + c, best[t]
            up = one > top
            second[t] = np.where(up, np.maximum(top, second[s] + c), np.maximum(second[t], one))
            best[t] = np.where(up, one, top)
            by[t] = np.where(up, np.arange(a, b), by[t])
        rows = np.arange(len(words))
        end = rows * wide + size
        at, count = np.where(spelt, rows * wide, end), np.zeros(len(words), np.int64)
        chosen = np.zeros((len(words), wide), "<i4")
        live = np.flatnonzero(at > rows * wide)
        while len(live):
            k = by[at[live]]
            count[live] += 1
            chosen[live, wide - count[live]] = ids[k]
            at[live] = source[k]
            live = live[at[live] > live * wide]
        packed, row = chosen.tobytes(), 4 * wide
        from_ = (np.arange(1, len(words) + 1) * row - 4 * count).tolist()
        with np.errstate(invalid="ignore"):
            scores, gaps = best[end].tolist(), (best[end] - second[end]).tolist()
        return [None if s else (packed[f : (w + 1) * row], x, g) for w, (s, f, x, g) in enumerate(zip(spelt.tolist(), from_, scores, gaps, strict=True))]


class _Known(dict):
    """What was learnt of words, in two generations: a full one becomes the older, which is looked at once more.

    Most words of a corpus come once. So a word is only marked when it is met and kept from the second time on; till
    the next texts are met, those of these texts are in ``fresh``.
    """

    def __init__(self, learn, most: int):
        self.learn, self.most, self.older, self.fresh = learn, most, {}, {}
        self.marks, self.marked = bytearray(CACHE_MARKS), 0

    def __missing__(self, word: str):
        found = self.fresh.get(word)
        if found is None:
            found = self.older.pop(word, None)
            if found is not None:
                self.keep(word, found)
            else:
                found = self.learn(word)
                if not self.meet(word, found):
                    if len(self.fresh) >= self.most:
                        self.fresh.clear()
                    self.fresh[word] = found
        return found

    def meet(self, word: str, found) -> bool:
        """Keep a word that was met before, else mark it; whether it was kept, or is too long to be."""
        if len(word) > CACHE_CHARS:
            return True
        at = hash(word) % CACHE_MARKS
        if self.marks[at]:
            self.keep(word, found)
            return True
        if self.marked >= CACHE_MARKS // 8:
            self.marks, self.marked = bytearray(CACHE_MARKS), 0
        self.marks[at] = 1
        self.marked += 1
        return False

    def keep(self, word: str, found) -> None:
        if len(self) >= self.most:
            self.older = dict(self)
            self.clear()
        self[word] = found


class Coder:
    """Encodes texts with a cache of words; one for each worker process."""

    def __init__(self, vocabulary: Vocabulary, n: int = N_BEST, caches: tuple[int, int] | None = None):
        self.vocabulary, self.n = vocabulary, n
        words, searched = caches or (CACHE_WORDS, CACHE_SEARCHED)
        # A word takes the blanks before it along; line ends and blanks at the end stand alone.
        self.cut = re.compile(r" *[^ \n]+|\n| +" if vocabulary.apart else r"(?s).+").findall
        lengths = np.array([len(t) for t in vocabulary.text], np.int64)
        self.lengths, self.places = lengths, np.cumsum(lengths) - lengths
        self.bytes = np.frombuffer(b"".join(vocabulary.text), np.uint8)
        self.known, self.trie = _Known(self.learn, words), Trie(vocabulary)
        self.searched = _Known(self.search, searched)

    def learn(self, word: str) -> tuple[bytes, float, float]:
        ids, score, gap = two_best(self.vocabulary, word)
        if gap < TIE:
            return self.options(word)[0][1], score, 0.0
        return struct.pack(f"<{len(ids)}i", *ids), score, gap

    def meet(self, texts: list[str]) -> list[list[str]]:
        """The words of some texts; new ones are learnt together, except those that are longer than the cache's, left to ``encode``."""
        known, older = self.known, self.known.older
        known.fresh = fresh = {}
        self.searched.fresh = {}
        cut = [self.cut(" " + text) for text in texts]
        new = set().union(*cut).difference(known, older)
        words = sorted((w for w in new if len(w) <= CACHE_CHARS), key=len)
        for a in range(0, len(words), MET_WORDS):
            part = words[a : a + MET_WORDS]
            for word, found in zip(part, self.trie.two_best(part), strict=True):
                if found is None:
                    found = self.learn(word)
                elif found[2] < TIE:
                    found = self.options(word)[0][1], found[1], 0.0
                if not known.meet(word, found):
                    fresh[word] = found
        return cut

    def options(self, word: str) -> list[tuple[float, bytes]]:
        """The word's n best: how far each lies under the best, and its packed ids; searched for the few words that need it."""
        return self.searched[word]

    def search(self, word: str) -> list[tuple[float, bytes]]:
        best = n_best(self.vocabulary, word, self.n)
        return [(s - best[0][0], struct.pack(f"<{len(ids)}i", *ids)) for s, ids in best]

    def decode(self, packed: bytes) -> bytes:
        """The UTF-8 bytes of packed ids, with the blank that encoding puts in front."""
        parts = []
        for a in range(0, len(packed), 4 * BLOCK_WORDS):
            ids = np.frombuffer(packed[a : a + 4 * BLOCK_WORDS], "<i4")
            n = self.lengths[ids]
            parts.append(self.bytes[np.repeat(self.places[ids] - np.cumsum(n) + n, n) + np.arange(n.sum())].tobytes())
        return b"".join(parts)

    def encode(self, text: str, words: list[str] | None = None) -> dict:
        """Ids and decoded bytes of the best segmentation; scores and packed ids, in parts, of the n best.

        ``words`` are the text's, where ``meet`` has cut it already.
        """
        if not text:
            return {"n": 0, "ids": b"", "plain": b" ", "scores": [0.0], "segmentations": [[b""]]}
        words = words or self.cut(" " + text)
        ids, total = [], 0.0
        small: list[tuple[float, int]] = []
        few = self.n - 1
        for a in range(0, len(words), BLOCK_WORDS):
            part = words[a : a + BLOCK_WORDS]
            packed, scores, gaps = zip(*map(self.known.__getitem__, part), strict=True)
            ids += packed
            total += math.fsum(scores)
            if len(part) > 50:
                g = np.fromiter(gaps, np.float64, len(gaps))
                near = np.flatnonzero(g <= np.partition(g, few - 1)[few - 1]).tolist() if few else []
                small += heapq.nsmallest(few, [(gaps[k], a + k) for k in near])
            else:
                small += [(g, a + k) for k, g in enumerate(gaps)]
            small = heapq.nsmallest(few, small)
        # The ids in parts: each of the chosen words by itself, and what lies between them.
        places = sorted(k for _, k in small)
        parts, last = [], 0
        for k in places:
            parts += [b"".join(ids[last:k]), ids[k]]
            last = k + 1
        parts.append(b"".join(ids[last:]))
        packed = b"".join(parts)
        options = [self.options(words[k]) for k in places]
        scores, segmentations = [], []
        for score, choice in combined(round(total, 6), options, self.n):
            one = list(parts)
            for k, c in enumerate(choice):
                one[2 * k + 1] = options[k][c][1]
            scores.append(score)
            segmentations.append(one)
        return {"n": len(packed) // 4, "ids": packed, "plain": self.decode(packed), "scores": scores, "segmentations": segmentations}


_CODERS: dict[tuple, Coder] = {}


def coder_of(model: str, vocabulary: Vocabulary, n: int = N_BEST, caches: tuple[int, int] | None = None) -> Coder:
    """The worker process's coder for a model: its cache lives on from task to task, unless ``let_go`` ends it."""
    if (model, n, caches) not in _CODERS:
        _CODERS.clear()
        _CODERS[model, n, caches] = Coder(vocabulary, n, caches)
    return _CODERS[model, n, caches]


def let_go() -> None:
    """Give the memory of the worker process's coder back to the system; worker processes outlive their stage."""
    _CODERS.clear()
    gc.collect()  # a coder and its caches refer to each other
    with suppress(AttributeError, OSError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def combined(total: float, options: list[list[tuple[float, bytes]]], n: int) -> list[tuple[float, tuple[int, ...]]]:
    """The n best sums of one option from each list, on top of ``total``, and the options chosen.

    Only the n - 1 words with the smallest gap can be in them: each alone gives a better sum than any other word.
    """
    sums: list[tuple[float, tuple[int, ...]]] = [(0.0, ())]
    for some in options:
        sums = sorted(((round(s + x, 9), (*c, k)) for s, c in sums for k, (x, _) in enumerate(some)), key=lambda y: (-y[0], y[1]))[:n]
    return [(round(total + s, 6), c) for s, c in sums]


def _sha(parts: list[bytes]) -> str:
    one = hashlib.sha256()
    for p in parts:
        one.update(p)
    return one.hexdigest()


ENCODED = "n_pieces bigint, ids binary, decoded string, n_best array<struct<score:double,ids:binary>>"
DIGESTS = "n_pieces bigint, ids_sha256 string, decoded_sha256 string, round_trip boolean, best_score double, margin double, n_best array<struct<score:double,ids_sha256:string>>"


def encode(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", model: str = MODEL, digests: bool = False, n: int = N_BEST, caches: tuple[int, int] | None = None, keep: bool = True) -> DataFrame:
    """Ids (32-bit, little endian), decoded text and all n best segmentations of every row; or digests of them.

    The driver reads the vocabulary and sends it along; its size is the model's and never grows with the data.
    Without ``keep`` a worker process holds no coder after a task: slower, but nothing is left for what runs next.
    """
    kind = docs.schema[doc_id].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary.load(model))
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    out = DIGESTS if digests else ENCODED
    names = ["doc_id", *(x.split()[0] for x in out.split(", "))]
    best = pa.list_(pa.struct([("score", pa.float64()), ("ids_sha256", pa.string()) if digests else ("ids", pa.binary())]))
    kinds = [pa.int64(), pa.string(), pa.string(), pa.bool_(), pa.float64(), pa.float64(), best] if digests else [pa.int64(), pa.binary(), pa.string(), best]

    def coded(batches):
        coder = coder_of(model, shared.value, n, caches)
        for batch in batches:
            for a in range(0, batch.num_rows, MET_TEXTS):
                ids, texts = batch.column(0).slice(a, MET_TEXTS), batch.column(1).slice(a, MET_TEXTS)
                columns: list[list] = [[] for _ in kinds]
                ahead = 0
                for at, text in enumerate(texts):
                    if at == ahead:
                        some, chars = [], 0
                        while ahead < len(texts) and chars < MET_CHARS:
                            some.append(texts[ahead].as_py())
                            chars += len(some[-1])
                            ahead += 1
                        cut = coder.meet(some)[::-1]
                    text = text.as_py()
                    got = coder.encode(text, cut.pop())
                    plain, s = got["plain"][1:], got["scores"]
                    if digests:
                        every = [{"score": x, "ids_sha256": _sha(p)} for x, p in zip(s, got["segmentations"], strict=True)]
                        row = (got["n"], every[0]["ids_sha256"], hashlib.sha256(plain).hexdigest(), plain == text.encode(), s[0], round(s[0] - s[1], 6) if len(s) > 1 else None, every)
                    else:
                        row = (got["n"], got["ids"], plain.decode(), [{"score": x, "ids": b"".join(p)} for x, p in zip(s, got["segmentations"], strict=True)])
                    for c, v in zip(columns, row, strict=True):
                        c.append(v)
                yield pa.RecordBatch.from_arrays([ids, *(pa.array(c, t) for c, t in zip(columns, kinds, strict=True))], names=names)

    def run(batches):
        try:
            yield from coded(batches)
        finally:
            if not keep:
                let_go()

    return rows.mapInArrow(run, f"doc_id {kind}, {out}")


def op8_sentencepiece(spark, sf_dir: str, model: str = MODEL) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), model=model, digests=True)


def pieces_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Last pipeline stage: every document as digests of its ids, which decode to its text."""
    return encode(docs, digests=True, caches=STAGE_CACHES, keep=False)
