"""The encoder's caches: bounded, and without any effect on results."""

import random

from balcut.llm import pieces


def test_words_met_once_are_not_kept_and_caches_stay_bounded(monkeypatch):
    monkeypatch.setattr(pieces, "CACHE_WORDS", 200)
    monkeypatch.setattr(pieces, "CACHE_SEARCHED", 20, raising=False)
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("aeinrst") for _ in range(rng.randint(2, 9))) + rng.choice(["", "é", "☃"])
    often = [word() for _ in range(300)]
    texts = [" ".join([f"{word()}{t}x{i}zq" for i in range(60)] + rng.sample(often, 40)) for t in range(60)]
    v = pieces.Vocabulary.load()
    held = pieces.Coder(v)
    for k in range(0, len(texts), 6):
        held.meet(texts[k : k + 6])
        for text in texts[k : k + 6]:
            alone = pieces.Coder(v)
            assert held.encode(text) == alone.encode(text)
        for cache, most in ((held.known, 200), (held.searched, 20)):
            assert len(cache) <= most and len(cache.older) <= most
    kept = {w.strip() for w in (*held.known, *held.known.older)}
    assert len(kept & set(often)) > 100 and not any(w.endswith("zq") for w in kept)


def test_words_of_texts_met_together_are_searched_once(monkeypatch):
    """op8: words with ties were searched when they were met and again when a text chose them."""
    searched, real = [], pieces.n_best
    monkeypatch.setattr(pieces, "n_best", lambda v, word, n: searched.append(word) or real(v, word, n))
    held = pieces.Coder(pieces.Vocabulary.load())
    texts = ["In&&& a$$$ and De%%%", "a$$$ Th$$$ é☃☃☃ In&&&"]
    held.meet(texts)
    got = [held.encode(text) for text in texts]
    assert " a$$$" in searched and len(searched) == len(set(searched))
    assert got == [pieces.Coder(held.vocabulary).encode(text) for text in texts]
