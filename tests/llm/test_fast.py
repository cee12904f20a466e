"""Shorter ways of operators 8 and 9 against the longer ones."""

import numpy as np


def test_plain_letters_skip_to_the_model():
    import public_tokenizers

    from segraph.llm import wavelet as W

    path = public_tokenizers.path("word_bpe_49k.json")
    c = W._Chunks(path)
    assert c.model is not None
    letters = [chr(x) for x in range(0x600) if chr(x).isalpha()]
    words = letters + [a + b + a for a, b in zip(letters, letters[7:])] + ["the", "tokenization", "größe", "naïve", "слово", "don't", "x1", "İ", "e\u0301t", "\u0345a", "ſt", "ǆ", "中文"]
    for w in words:
        part = w.encode().lower()
        assert c._encode(part) == c.tok.encode(part.decode(), add_special_tokens=False).ids, w

    class Refuses:
        def encode(self, *_, **__):
            raise AssertionError("a word of plain letters went through the whole library")

    c.tok = Refuses()
    assert all(c._encode(w.encode()) for w in ("the", "größe", "слово"))


def test_hash_lookup_is_the_binary_search():
    import public_tokenizers

    from segraph.llm import pieces, sp_sampling as S

    hs = S._Hashes(pieces.load(public_tokenizers.path("piece_bpe_32k.model")))
    near = [hs.hash, hs.hash + np.uint64(1), hs.hash - np.uint64(1), np.array([0, 2**64 - 1], np.uint64), np.random.default_rng(5).integers(0, 2**64, 100_000, dtype=np.uint64)]
    h = np.concatenate(near)
    assert (hs.find(h) == np.minimum(np.searchsorted(hs.hash, h), len(hs.hash) - 1)).all()


def test_words_that_came_twice_stay_and_sample_alike():
    import public_tokenizers

    from segraph.llm import pieces, sp_sampling as S

    lat = S.Lattices(pieces.load(public_tokenizers.path("piece_bpe_32k.model")))
    texts = ["the größe of 12 слово.", "once only, ☃ the größe", "the größe again and again"]
    rows = [pieces.units_of(t) for t in texts]
    keys = np.arange(3, dtype=np.uint64) + np.uint64(9)
    want = S.sample_rows(lat, rows, 3, keys)
    S.sample_rows(lat, rows[:1], 3, keys[:1])
    lat.shrink(10**6)
    assert set(lat.root) == set(rows[0]) and lat.size < sum(len(w) for w in rows[0]) ** 2
    added = []
    lat._add = lambda words: (added.extend(words), S.Lattices._add(lat, words))
    got = S.sample_rows(lat, rows, 3, keys)
    assert sorted(added) == sorted(set(rows[1] + rows[2]) - set(rows[0]))
    ids = S._ids(lat, got[6], got[5])[0]
    fresh = S.Lattices(lat.vocab)
    again = S.sample_rows(fresh, rows, 3, keys)
    assert (ids == S._ids(fresh, again[6], again[5])[0]).all()
    for a, b, c in zip(got[:6], want[:6], again[:6]):
        assert (a == b).all() and (a == c).all()
    lat.shrink(0)
    assert not lat.root and lat.size == 0
