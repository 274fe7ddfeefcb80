"""The pure kernels: suffixes, factors, codes and baselines against definitions and brute force."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from drstore.operators import baselines, bulk, codecs, factorize, lz, semistatic, suffix
from drstore.operators.dictionary import Dictionary
from drstore.operators.factorize import decode_document, decode_range, factor_document
from drstore.operators.suffix import GramIndex, Searcher, longest_match_naive, rank_array, suffix_array

D, X = b"cabbaabba", b"bbaancabb"


def searcher(d: bytes) -> Searcher:
    return Searcher(d, suffix_array(d))


def test_worked_example():
    sa = suffix_array(D)
    assert (sa + 1).tolist() == [9, 5, 6, 2, 8, 4, 7, 3, 1]
    assert (rank_array(sa) + 1).tolist() == [9, 4, 8, 6, 2, 3, 7, 5, 1]
    # "bba" (rank 7) also begins with the first three bytes, so the third interval still has both
    assert [got and (got[0] + 1, got[1] + 1) for _, got in searcher(D).trace(X)] == [(5, 8), (7, 8), (7, 8), (8, 8), None]
    assert factor_document(X, searcher(D)) == ([2, ord("n"), 0], [4, 0, 4])
    assert decode_document([2, ord("n"), 0], [4, 0, 4], D) == X


texts = st.one_of(st.binary(max_size=60), st.text("ab", max_size=60).map(str.encode), st.text("abcd", max_size=80).map(str.encode), st.integers(0, 40).map(lambda n: b"a" * n))


@settings(max_examples=150, deadline=None)
@given(texts, texts)
def test_factors_meet_the_definition(d, x):
    s = searcher(d)
    assert suffix_array(d).tolist() == sorted(range(len(d)), key=lambda p: d[p:])
    pos, length = factor_document(x, s)
    assert decode_document(pos, length, d) == x
    i = 0
    for p, k in zip(pos, length, strict=True):
        assert (p, k) == longest_match_naive(d, x, i) if k else x[i : i + 1] not in d
        i += k or 1
    if x and d:
        assert s.occurrences(x[:2]) == sum(d.startswith(x[:2], p) for p in range(len(d)))


@settings(max_examples=150, deadline=None)
@given(texts, st.lists(texts, max_size=30))
def test_many_documents_at_once(d, bodies):
    s = searcher(d)
    bulk.WINDOW, window = 32, bulk.WINDOW
    try:
        pos, length, cuts = bulk.Bulk(s).factors(bodies)
    finally:
        bulk.WINDOW = window
    for x, i, j in zip(bodies, cuts[:-1], cuts[1:], strict=True):
        assert (pos[i:j].tolist(), length[i:j].tolist()) == factor_document(x, s)


@settings(max_examples=60, deadline=None)
@given(texts, texts)
def test_gram_index_agrees_on_long_matches(d, x):
    s, g = searcher(d), GramIndex(d, 3)
    for i in range(len(x)):
        p, k = s.longest_match(x, i)
        if k >= 3:
            assert g.longest_match(x, i) == (p, k)


def test_long_matches_and_ends():
    d = b"xyz" * 200 + bytes(range(256))
    s = searcher(d)
    for x in (d, d[100:500], d[-1:], b"xyz" * 300, b"", b"\x00\xff"):
        pos, length = factor_document(x, s)
        assert decode_document(pos, length, d) == x
    assert factor_document(b"abc", searcher(b"")) == ([97, 98, 99], [0, 0, 0])
    pos, length = (np.array(v) for v in factor_document(d[37:420], s))
    assert decode_range(pos, length, d, 10, 64) == d[47:111]


NUMBERS = [0, 1, 127, 128, 16383, 16384, 2**21 - 1, 2**21, 2**28 - 1, 2**28, 2**32 - 1]


@pytest.mark.parametrize("code", list(codecs.CODES))
def test_codes_invert(code):
    enc, dec = codecs.CODES[code]
    r = random.Random(1)
    for v in ([], [0], NUMBERS, [5] * 300, [r.randrange(2 ** r.randrange(1, 33)) for _ in range(700)]):
        assert dec(enc(np.array(v, np.int64))).tolist() == v
    assert len(codecs.enc_v(np.array(NUMBERS))) == 1 + 1 + 1 + 2 + 2 + 3 + 3 + 4 + 4 + 5 + 5


@pytest.mark.parametrize("codec", [*codecs.GRID, "Zi", "US", "UP", "FV"])
def test_pair_codecs_invert(codec):
    pos, length = np.array([3, 110, 0, 70000]), np.array([4, 0, 4, 300])
    p, k = codecs.encode_pairs(pos, length, codec)
    a, b = codecs.decode_pairs(p, k, codec)
    assert a.tolist() == pos.tolist() and b.tolist() == length.tolist()


@pytest.mark.parametrize("name", ["raw", "zlib", "gzip", "deflate9", "deflate14", "lzma", "lzma-128", "bz2"])
def test_block_codecs_open_a_part(name):
    x = b"some text that repeats, some text that repeats " * 50
    squeeze, open_ = baselines.codec(name)
    assert open_(squeeze(x), len(x)) == x
    assert open_(squeeze(x), 100)[:100] == x[:100]
    assert open_(squeeze(b""), 0) == b""


@settings(max_examples=60, deadline=None)
@given(texts.map(lambda x: x * 3))
def test_other_methods_invert(x):
    assert baselines.undo_two_pass(baselines.two_pass(x, block=8)) == x
    assert lz.undo_window_lz(lz.window_lz(x)) == x
    assert lz.undo_pair_grammar(*lz.pair_grammar(x, 20)) == x
    parts = lz.end_aligned(x)
    assert lz.open_end_aligned(parts, 0, len(x)) == x
    assert lz.open_end_aligned(parts, len(x) // 3, len(x) // 4) == x[len(x) // 3 : len(x) // 3 + len(x) // 4]


def test_huffman_and_dense_codes():
    freq = {"a": 50, "b": 20, "c": 10, "d": 10, "e": 5, "f": 5}
    lengths = semistatic.huffman_lengths(freq)
    assert sum(2.0**-n for n in lengths.values()) == 1
    codes = semistatic.canonical_codes(lengths)
    assert not any(a != b and b.startswith(a) for a in codes.values() for b in codes.values())
    bits = sum(f * lengths[s] for s, f in freq.items())
    table: dict[int, int] = {}
    for f in freq.values():
        table[f] = table.get(f, 0) + 1
    assert sum(w * n for w, n in semistatic._lengths_by_count(table, 2)) == bits
    r = random.Random(3)
    big = {f"w{i}": r.randrange(1, 40) for i in range(700)}
    table = {}
    for f in big.values():
        table[f] = table.get(f, 0) + 1
    for arity in (2, 128, 256):
        lengths = semistatic.huffman_lengths(big, arity)
        assert sum(w * n for w, n in semistatic._lengths_by_count(table, arity)) == sum(big[s] * n for s, n in lengths.items())
    tagged = semistatic.tagged_codes(semistatic.huffman_lengths(big, 128))
    text = ["w1", "w2", "w3", "w2", "w3", "w699"]
    coded = b"".join(tagged[s] for s in text)
    hits = semistatic.search_tagged(coded, tagged, ["w2", "w3"])
    assert len(hits) == 2
    for rank in (0, 127, 128, 16511, 16512, 2113663, 2113664):
        code = semistatic.dense_code(rank)
        assert semistatic.undense(code) == [rank] and len(code) == (1 if rank < 128 else 2 if rank < 16512 else 3 if rank < 2113664 else 4)
    words = [r.choice("the of and to in ab cd ef gh".split()) for _ in range(400)] + [f"x{i}" for i in range(300)] * 2
    for light in (False, True):
        assert semistatic.undo_dynamic_dense(semistatic.dynamic_dense(words, light), light) == words


def test_dictionary_versions_keep_places(tmp_path):
    d = Dictionary(b"abcabc")
    e = d.extend(b"xyz")
    assert e.version == 1 and e.sizes == [6, 9] and e.data.startswith(d.data)
    e.save(str(tmp_path / "d"))
    back = Dictionary.load(str(tmp_path / "d"))
    assert back.data == e.data and back.sizes == e.sizes and back.sa.tolist() == e.sa.tolist()


def test_window_lz_tries_the_whole_window():
    x = b"abcdefgh" + b"".join(b"abc" + bytes([65 + i % 26, 48 + i % 10]) for i in range(100)) + b"\xffabcdefgh"
    parts = lz.window_lz(x)
    assert lz.undo_window_lz(parts) == x and any(k >= 8 and d == len(x) - 8 for d, k, _ in parts)


@given(st.text("ab", max_size=60))
def test_end_aligned_phrases_are_the_longest(text):
    x = text.encode()
    i, ends = 0, []
    for phrase, k, c in lz.end_aligned(x):
        fits = [(j, m) for m in range(len(x) - i - 1, 0, -1) for j, e in enumerate(ends) if e >= m and x[e - m : e] == x[i : i + m]]
        assert (phrase, k) == (fits[0] if fits else (0, 0))
        i += k + (c >= 0)
        ends.append(i)
    assert i == len(x)


def test_suffixes_are_sorted_part_by_part(monkeypatch):
    monkeypatch.setattr(suffix, "SORTED", 16)
    monkeypatch.setattr(suffix, "MAPPED", 64)
    for d in (b"", b"a", bytes(100), b"ab" * 90, b"cabbaabba" * 30 + b"\0", bytes(range(256)) * 2, b"aaab" * 40 + b"\xff\0\0"):
        assert suffix_array(d).tolist() == sorted(range(len(d)), key=lambda p: d[p:])


def test_sorting_suffixes_takes_little_memory():
    import tracemalloc

    d = np.random.default_rng(0).integers(97, 105, 1 << 23, np.uint8).tobytes()
    tracemalloc.start()
    suffix_array(d)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 20 * len(d)


@pytest.mark.parametrize("alphabet", [b"ab", b"\0\1", bytes(range(97, 105))])
def test_leftmost_factors_of_many_documents(alphabet, monkeypatch):
    r = random.Random(7)
    text = lambda n: bytes(r.choice(alphabet) for _ in range(n))
    d = text(3000)
    docs = [text(r.randrange(80)) for _ in range(30)] + [d[5:70], d[7:400] + b"z", b""]
    s = Searcher(d, suffix_array(d))
    want = [factor_document(x, s, "leftmost") for x in docs]
    monkeypatch.setattr(factorize, "factor_document", None)  # not one by one
    pos, length, cuts = factorize.factor_batch(docs, s, "leftmost")
    assert [(pos[i:j].tolist(), length[i:j].tolist()) for i, j in zip(cuts[:-1], cuts[1:], strict=True)] == want
    assert all(d.find(x[:k]) == p for x, (ps, ks) in zip(docs, want, strict=True) for p, k in zip(ps[:1], ks[:1], strict=True) if k)


def test_opening_aligned_phrases_copies_runs():
    x = bytes(random.Random(5).choice(b"abcd") for _ in range(2000)) * 20
    parts = lz.end_aligned(x)

    class Counted(list):
        asked = 0

        def __getitem__(self, i):
            Counted.asked += 1
            return super().__getitem__(i)

    assert lz.open_end_aligned(Counted(parts), 0, len(x)) == x and lz.open_end_aligned(parts, 777, 9000) == x[777:9777]
    assert Counted.asked < len(x) // 4


def test_walks_that_step_together_meet_matches_of_any_length(monkeypatch):
    monkeypatch.setattr(bulk, "WINDOW", 700)
    r = random.Random(9)
    d = bytes(r.choice(b"abc") for _ in range(5000))
    docs = [d[100:900], b"", d[3000:3100] + d[10:400] + b"?", bytes(r.choice(b"abc") for _ in range(1500)), b"?"]
    s = Searcher(d, suffix_array(d))
    pos, length, cuts = factorize.factor_batch(docs, s)
    assert [(pos[i:j].tolist(), length[i:j].tolist()) for i, j in zip(cuts[:-1], cuts[1:], strict=True)] == [factor_document(x, s) for x in docs]
    assert length.max() > bulk.DEEP
