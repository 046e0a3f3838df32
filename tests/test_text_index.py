import random

import numpy as np
import pytest

from treeloom.text.fm import PatternError, RangeReport, TextIndex, merge
from treeloom.text.pssm import best_scores, score
from treeloom.text.rank import build_rank


def test_worked_example():
    ix = TextIndex.build([b"discontinued"], 3)
    low, high = ix.search("n")
    assert (low + 1, high) == (8, 9)
    assert ix.lf(np.array([7]))[0] + 1 == 10 and ix.lf(np.array([9]))[0] + 1 == 2
    assert ix.locate(np.array([7]))[1][0] + 1 == 6


@pytest.mark.parametrize("kind", ["blocks", "wavelet", "huffman", "runs"])
def test_rank_and_select(kind):
    rng = np.random.default_rng(1)
    seq = rng.choice([0, 3, 7, 200], 700, p=[0.1, 0.6, 0.2, 0.1]).astype(np.uint8)
    r = build_rank(seq, kind)
    for c in (0, 3, 7, 200, 9):
        want = np.concatenate([[0], np.cumsum(seq == c)])
        assert r.rank(c, np.arange(701)).tolist() == want.tolist()
    for c in (0, 3, 7, 200):
        at = np.nonzero(seq == c)[0]
        assert [r.select(c, j) for j in (1, 5, len(at))] == [at[0], at[4], at[-1]]


def test_predicates_against_the_texts():
    rng = random.Random(3)
    for trial in range(60):
        texts = [bytes(rng.choice(b"abc") for _ in range(rng.randint(0, 12))) for _ in range(rng.randint(1, 9))]
        kind, l = rng.choice(["blocks", "wavelet", "huffman", "runs"]), rng.choice([1, 4, 64])
        k = rng.randint(0, len(texts))
        ix = TextIndex.build(texts, l, kind) if trial % 2 else merge(TextIndex.build(texts[:k], l, kind), TextIndex.build(texts[k:], l, kind))
        ix = TextIndex.unpack(ix.pack())
        assert [ix.extract(i) for i in range(len(texts))] == texts
        for p in (b"a", b"ab", b"abc", b"d", b"bb", texts[0] or b"c"):
            ids = lambda f: [i for i, t in enumerate(texts) if f(t)]
            assert ix.global_count(p) == sum(t[i : i + len(p)] == p for t in texts for i in range(len(t)))
            assert ix.contains(p).tolist() == ids(lambda t: p in t)
            assert ix.starts_with(p).tolist() == ids(lambda t: t.startswith(p))
            assert ix.ends_with(p).tolist() == ids(lambda t: t.endswith(p)) and ix.ends_with_count(p) == len(ix.ends_with(p))
            assert ix.equals(p).tolist() == ids(lambda t: t == p)
            for op, f in (("<", lambda t: t < p), ("<=", lambda t: t <= p), (">", lambda t: t > p), (">=", lambda t: t >= p)):
                assert ix.compare(op, p).tolist() == ids(f)


def test_at_most_stops_at_the_pattern():
    assert TextIndex.build([b"ab", b"abc"]).at_most("ab").tolist() == [0]


def test_patterns_are_checked_and_collections_may_be_empty():
    empty = TextIndex.build([])
    assert empty.global_count("a") == 0 and empty.contains("a").tolist() == []
    for bad in ("", "a\0"):
        with pytest.raises(PatternError):
            empty.search(bad)
    assert TextIndex.build([b"aaaa"]).global_count("aa") == 3


def test_range_report_and_matrix_search():
    rng = random.Random(8)
    doc = np.array([rng.randrange(40) for _ in range(40)])
    for _ in range(40):
        a, b = sorted((rng.randint(0, 40), rng.randint(0, 40)))
        x, y = sorted((rng.randint(0, 40), rng.randint(0, 40)))
        assert RangeReport(doc).report(a, b, x, y) == sorted(v for v in doc[a:b].tolist() if x <= v <= y)
    texts = ["".join(rng.choice("ACGT") for _ in range(30)) for _ in range(5)]
    w = [{c: rng.randint(-5, 9) for c in "ACGT"} for _ in range(5)]
    ix = TextIndex.build([t.encode() for t in texts])
    got = ix.locate(ix.matrix([{ord(c): x for c, x in col.items()} for col in w], 20))
    want = [(i, j) for i, t in enumerate(texts) for j in range(26) if score(w, t[j : j + 5]) > 20]
    assert sorted(zip(got[0].tolist(), got[1].tolist())) == want
    assert [b > 20 for b in best_scores(texts, w)] == [any(k == i for k, _ in want) for i in range(5)]


def test_matrix_score_of_the_example():
    w = [{"A": 0, "G": 4, "C": 0, "T": 0}, {"A": 6, "G": 0, "C": 6, "T": 0}, {"A": 0, "G": 10, "C": 0, "T": 0}, {"A": 0, "G": 0, "C": 0, "T": 1}]
    assert score(w, "ACGA") == 16


def test_a_search_counts_the_symbols_of_its_pattern_only():
    rng = random.Random(61)
    texts = [bytes(rng.choice(b"abcdefgh") for _ in range(rng.randint(0, 300))) for _ in range(40)]
    ix = TextIndex.unpack(TextIndex.build(texts, 4).pack())
    low, high = ix.search(b"ab")
    assert high - low == sum(t.count(b"ab") for t in texts)
    assert set(ix.rank._own) == {ord("a"), ord("b")} and ix.rank._all is None
    places = np.arange(ix.n + 1)
    for c in (*b"abh", 0, ord("z")):
        assert ix.rank.rank(c, places).tolist() == np.concatenate([[0], np.cumsum(ix.column == c)]).tolist()
        assert ix.rank.ranks(np.full(ix.n, c), places[:-1]).tolist() == ix.rank.rank(c, places[:-1]).tolist()
    assert ix.rank.bits() == 8 * (ix.rank.seq.nbytes + ix.rank.before.nbytes)
