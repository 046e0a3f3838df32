import hashlib
import itertools
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from tests.llm.helpers import EDGE, docs_of, edge_docs, empty_docs
from treeloom.llm import mixing, near, repeats, sharding
from treeloom.llm import urls as urls_module
from treeloom.llm.bpe import SHORT_WORD, WordBpe, encode_documents
from treeloom.llm.language import best_paths, fit, identify, scripts_of
from treeloom.llm.lines import drop_recurring_lines, lead_of, line_segments
from treeloom.llm.mixing import bisect_exponent, entropy, mix_index, mix_sources, repetition, weigh
from treeloom.llm.quality import BASE, RULES, Measured, cascade_report, judge_quality, keep_good, ordered, sampled
from treeloom.llm.queries import URL_RULES, VOCABULARY
from treeloom.llm.sharding import communication_matrix, hypergeometric, shard_digest, shard_rows
from treeloom.llm.topk import exact_top_k
from treeloom.llm.urls import DigestArray, host_and_path, judge_urls

RNG = random.Random(4)
WORDS = ["".join(RNG.choice("abcdefgh") for _ in range(RNG.randint(2, 7))) for _ in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


# --- edge rows through every operator on documents


@pytest.mark.parametrize(
    "run",
    [
        judge_quality, keep_good, shard_digest, drop_recurring_lines, repeats.remove_repeats, near.near_duplicates, near.drop_near_duplicates,
        lambda d: mix_sources(d, max_repetition=2.0), lambda d: mix_index(d, target_entropy=0.5, budget=50), lambda d: encode_documents(d, VOCABULARY),
        lambda d: identify(d.select("doc_id", "text"), fit(d)),
    ],
)
def test_awkward_and_empty_tables(spark, run):
    assert run(empty_docs(spark)).count() == 0
    extra = edge_docs(spark).withColumns({c: F.lit(7) for c in ("shard", "slot", "epoch", "score", "kept", "row", "n_lines", "drop", "weight", "key", "label")})
    assert run(extra).count() >= 0
    assert len(run(edge_docs(spark)).collect()) >= 0


def test_every_row_is_answered(spark):
    for run in (judge_quality, shard_digest, drop_recurring_lines, repeats.remove_repeats, near.near_duplicates, lambda d: encode_documents(d, VOCABULARY)):
        assert run(edge_docs(spark)).count() == len(EDGE)


# --- line templates


def test_recurring_lines_stay_once(spark):
    rng = random.Random(1)
    foot = "all rights reserved by the owner of page {} in the year {}"
    texts = [prose(rng, 30) + "\n" + foot.format(i, 1990 + i) + "\n" + prose(rng, 25) for i in range(8)]
    out = {r["doc_id"]: r for r in drop_recurring_lines(docs_of(spark, texts)).collect()}
    assert out[0]["text"] == texts[0] and out[0]["n_dropped"] == 0
    for i in range(1, 8):
        assert out[i]["n_dropped"] == 1 and out[i]["text"].split("\n") == [texts[i].split("\n")[k] for k in (0, 2)]


def test_a_variable_field_without_digits_is_generalised(spark):
    line = "posted on this forum by {} with regards to all of you"
    texts = [line.format(w) + "\n" + prose(random.Random(w), 20) for w in WORDS[:7]]
    assert sorted(r["n_dropped"] for r in drop_recurring_lines(docs_of(spark, texts)).collect()) == [0, 1, 1, 1, 1, 1, 1]


def test_two_scattered_fields_and_short_lines_are_generalised(spark):
    rng = random.Random(60)
    texts = ["today we thank {} for the order which you have sent to {} by mail last week".format(rng.choice(WORDS), rng.choice(WORDS)) + "\n" + prose(rng, 20) for i in range(7)]
    assert sorted(r["n_dropped"] for r in drop_recurring_lines(docs_of(spark, texts)).collect()) == [0, 1, 1, 1, 1, 1, 1]
    texts = [f"user {w} logged in today\n" + prose(rng, 20) for w in WORDS[:7]]
    assert sorted(r["n_dropped"] for r in drop_recurring_lines(docs_of(spark, texts)).collect()) == [0, 1, 1, 1, 1, 1, 1]
    texts = [f"{w} {v} it is" + "\n" + prose(rng, 20) for w, v in zip(WORDS[:7], WORDS[7:])]
    assert all(r["n_dropped"] == 0 for r in drop_recurring_lines(docs_of(spark, texts)).collect())


def test_segments_cover_the_tokens_behind_the_lead():
    for n in range(1, 60):
        words = [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}".encode() for i in range(n)]
        tokens, leaf, parts = line_segments(b" ".join(words))
        assert tokens == n and len(parts) == min(6, n - lead_of(n))
        for q in range(n - lead_of(n)):
            other = list(words)
            other[lead_of(n) + q] = b"other"
            _, same, changed = line_segments(b" ".join(other))
            assert same == leaf and [i for i, (x, y) in enumerate(zip(parts, changed)) if x != y] == [q * len(parts) // (n - lead_of(n))]


def test_rare_lines_stay(spark):
    texts = ["same line here today\n" + prose(random.Random(i), 20) for i in range(4)]
    assert all(r["n_dropped"] == 0 for r in drop_recurring_lines(docs_of(spark, texts)).collect())


# --- sharding


def test_matrix_has_its_margins_and_is_fair():
    m = communication_matrix([5, 9, 6], [7, 7, 6], 3)
    assert m.sum(axis=1).tolist() == [5, 9, 6] and m.sum(axis=0).tolist() == [7, 7, 6]
    mean = sum(communication_matrix([50, 50], [30, 70], s)[0, 0] for s in range(400)) / 400
    assert abs(mean - 15) < 0.5


def test_own_hypergeometric_agrees_with_numpy():
    rng, ref = random.Random(2), np.random.default_rng(2)
    mine = [hypergeometric(rng, 40, 60, 25) for _ in range(4000)]
    theirs = ref.hypergeometric(40, 60, 25, 4000)
    assert abs(np.mean(mine) - theirs.mean()) < 0.15 and abs(np.std(mine) - theirs.std()) < 0.15
    assert 0 <= hypergeometric(rng, 10**12, 10**12, 10**6) <= 10**6
    assert hypergeometric(rng, 0, 5, 3) == 0 and hypergeometric(rng, 5, 0, 3) == 3


@pytest.mark.parametrize("n", [1, 5, 1000, 20_000])
def test_shards_are_exact_and_slots_gapless(spark, n):
    got = shard_rows(spark.range(n), 16, 1).toPandas()
    sizes = got.groupby("shard").size().reindex(range(16), fill_value=0)
    assert len(got) == n and got.id.nunique() == n and sizes.max() - sizes.min() <= 1
    for _, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    again = shard_rows(spark.range(n).repartition(3), 16, 1).toPandas()
    assert got.sort_values("id").slot.tolist() == again.sort_values("id").slot.tolist()


def test_many_equal_rows_are_dealt_and_buckets_keep_the_order(spark, monkeypatch):
    monkeypatch.setattr(sharding, "BLOCK_ROWS", 64)
    monkeypatch.setattr(sharding, "MAX_BLOCKS", 4)
    df = spark.range(3000).select(F.when(F.col("id") < 1000, -1).otherwise(F.col("id")).alias("h"), F.lit(1).alias("rank"))
    got = shard_rows(df, 7, 3).toPandas()
    assert list(got.columns) == ["h", "rank", "shard", "slot"] and sorted(got.h) == sorted([-1] * 1000 + list(range(1000, 3000)))
    for n, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g))) and abs(len(g) - 3000 / 7) < 1 and 90 < (g.h == -1).sum() < 200, n


def test_shard_digest_by_definition(spark):
    texts = ["é", "", None, "a b"] * 40
    got = shard_digest(docs_of(spark, texts)).toPandas()
    for r in got.itertuples():
        raw = (texts[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32, r.law) == (len(raw) + 1, zlib.crc32(raw), "rows") and got.grown_shard.isna().all()
    assert sorted(got.doc_id) == list(range(160)) and sorted(got.groupby("shard").size()) == [10] * 16
    assert sorted(zip(got.shard, got.slot)) == [(s, i) for s in range(16) for i in range(10)]


# --- quality


def test_the_sample_comes_from_all_files_and_the_order_can_be_read(spark):
    docs = spark.createDataFrame([(i, "w " * 60 + str(i)) for i in range(2000)], "doc_id long, text string").repartitionByRange(8, "doc_id")
    ids = [int(t.split()[-1]) for t in sampled(docs, 64)]
    assert len(set(ids)) == 64 and min(ids) < 400 and max(ids) > 1600 and ids == [int(t.split()[-1]) for t in sampled(docs.repartition(3), 64)]
    report = cascade_report(docs).toPandas()
    assert list(report.place) == list(range(1, len(RULES) + 1)) and set(report.rule) == {r.name for r in RULES}
    worth = (report.selectivity + 1e-4) / (report.cost_us / 1e6 + 1e-9)
    assert worth.is_monotonic_decreasing


def test_measures_by_definition():
    rng = random.Random(9)
    for _ in range(200):
        t = "".join(rng.choice("ab#é \n\t!|") for _ in range(rng.randint(0, 60)))
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        m = Measured(t)
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        grams = Counter(zip(w, w[1:], w[2:]))
        covered = {i + k for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for k in range(3)}
        assert (m.n_words, m.word_chars, m.n_dup_lines, m.n_repeat_words) == (len(w), sum(map(len, w)), len(lines) - len(set(lines)), len(covered))
        assert m.n_symbols == len(re.findall(r"[#*$%&|<>]", t))


def test_order_changes_no_verdict_and_goes_by_worth(spark):
    found = [(r.name, 1.0 if r.name == "symbols" else 0.1, 0.5 if r.name == "marks" else 0.01) for r in RULES]
    assert ordered(RULES, found)[0].name == "marks" and ordered(RULES, found)[-1].name == "symbols"
    rng = random.Random(3)
    texts = [prose(rng, 80), prose(rng, 20), "a!! " * 90, " ".join(f"{w}###" for w in WORDS[:90]), " ".join(WORDS[:60]) + "\n" + ("x y\n" * 80)]
    docs = docs_of(spark, texts)
    kept = {r["doc_id"]: r["kept"] for r in judge_quality(docs).collect()}
    want = {i: not BASE.rejects(Measured(t)) and not any(r.rejects(Measured(t)) for r in RULES) for i, t in enumerate(texts)}
    assert kept == want and kept[0] and not any(kept[i] for i in (1, 2, 3))
    assert {r["doc_id"] for r in keep_good(docs).collect()} == {i for i, k in want.items() if k}


# --- mixing


def test_bisection_meets_its_targets():
    tokens = [900, 60, 30, 10]
    assert abs(entropy(bisect_exponent(tokens, target_entropy=1.0).weights) - 1.0) < 1e-6
    assert abs(repetition(bisect_exponent(tokens, max_repetition=3.0)) - 3.0) < 1e-6
    assert bisect_exponent(tokens, max_repetition=1.0).exponent == pytest.approx(1.0)
    assert weigh(tokens, 1.0).weights == pytest.approx([0.9, 0.06, 0.03, 0.01])


def test_budgets_are_met_and_passes_are_permutations(spark):
    rng = random.Random(6)
    rows = [(i, prose(rng, rng.randint(1, 30)), "en", "big" if i % 3 else f"small{i % 9}", 0) for i in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    tokens = {r[0]: len(r[1].split()) for r in rows}
    got = mix_index(docs, max_repetition=2.0, budget=8000).toPandas()
    for source, g in got.groupby("source"):
        spent = sum(tokens[d] for d in g.doc_id)
        assert g.weight.iloc[0] * 8000 - 30 <= spent <= g.weight.iloc[0] * 8000 + 1
        for _, e in g.groupby("epoch"):
            assert sorted(e.position) == list(range(len(e))) and e.doc_id.is_unique
            assert e.sort_values("position").mix_order.is_monotonic_increasing
    assert set(mix_index(docs, max_repetition=2.0).toPandas().doc_id) == set(tokens)


def mix_by_definition(rows, max_repetition, seed=0):
    """(source, doc_id, epoch, order) that a mixture takes, document by document."""

    def order(epoch, doc_id):
        h = 42
        for data in (struct.pack("<i", seed), struct.pack("<i", epoch), struct.pack("<q", doc_id)):
            h = xxhash.xxh64_intdigest(data, h)
        return h - 2**64 if h >= 2**63 else h

    tokens = {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t, _, _, _ in rows}
    sources = defaultdict(list)
    for i, _, _, s, _ in rows:
        sources[s].append(i)
    names = list(sources)
    sums = [sum(tokens[i] for i in sources[s]) for s in names]
    w = bisect_exponent(sums, max_repetition=max_repetition)
    budget = max(t / x for t, x in zip(sums, w.weights) if x)
    out = []
    for s, t, x in zip(names, sums, w.weights):
        whole = int(x * budget / t + 1e-9) if t else 1
        left = int(x * budget - whole * t) if t else 0
        out += [(s, i, e, order(e, i)) for e in range(whole) for i in sources[s]]
        for i in sorted(sources[s], key=lambda i: order(whole, i)):
            left -= tokens[i]
            if left < 0 or not t:
                break
            out.append((s, i, whole, order(whole, i)))
    return sorted(out, key=str)


@pytest.mark.parametrize("block", [4096, 16])
def test_mixture_by_definition(spark, monkeypatch, block):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", block)
    rng = random.Random(61)
    rows = [(i, prose(rng, rng.randint(1, 30)) if i % 50 else None, "en", ["big", "mid", None][min(2, rng.randint(0, 9) // 4)] if i > 20 else f"tiny{i}", 0) for i in range(1200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(4)
    got = mix_index(docs, max_repetition=2.0).toPandas()
    got["source"] = got.source.where(got.source.notna(), None)
    assert sorted(((r.source, r.doc_id, r.epoch, r.mix_order) for r in got.itertuples()), key=str) == mix_by_definition(rows, 2.0)
    # every prefix of the mixture has the weights of the whole
    got = got.sort_values("mix_at")
    assert got.mix_at.between(0, 1 + 1e-9).all()
    big = (got.source == "big").to_numpy()
    for part in (0.25, 0.5, 0.75):
        assert abs(big[: int(len(big) * part)].mean() - big.mean()) < 0.06
    assert sorted(mix_sources(docs, max_repetition=2.0).toPandas().doc_id) == sorted(got.doc_id)


def test_many_sources_meet_an_entropy(spark):
    rows = [(i, "w " * (1 + 40 * (i % 300 == 0)), f"host{i % 300}") for i in range(3000)]
    docs = spark.createDataFrame([(i, t, "en", s, 0) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    target = 5.5
    got = mix_index(docs, target_entropy=target).select("source", "weight", "exponent").distinct().toPandas()
    assert len(got) == 300 and abs(entropy(list(got.weight)) - target) < 1e-6 and abs(got.weight.sum() - 1) < 1e-9
    sums = Counter()
    for _, t, s in rows:
        sums[s] += len(t.split())
    assert abs(got.exponent.iloc[0] - bisect_exponent(list(sums.values()), target_entropy=target).exponent) < 1e-9


# --- exact top-k


def test_top_k_by_brute_force(spark):
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(0, 0.3, 8)], 0) for i in range(400)]
    rows += [(1000 + i, rows[7][1], 0) for i in range(40)] + [(2000, None, 0), (2001, [1.0, None] + [0.0] * 6, 0), (2002, [float("nan")] * 8, 0), (2003, [1.0, 2.0], 0), (2004, [], 0), (2100, [3e5] * 8, 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = defaultdict(list)
    for r in exact_top_k(df, df.filter("vec_id % 100 = 0"), 10, block_rows=64, chunk_queries=3).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    whole = {i: [int(np.floor(np.float64(np.float32(x)) * 1024)) for x in v] for i, v, _ in rows if v and all(x is not None and np.isfinite(x) for x in v)}
    for q in [i for i in whole if i % 100 == 0]:
        scores = sorted(((-sum(a * b for a, b in zip(whole[q], v)), i) for i, v in whole.items() if i != q and len(v) == len(whole[q])))[:10]
        assert got[q] == [(i, -s) for s, i in scores], q
    assert exact_top_k(df.limit(0), df.limit(0)).count() == 0


# --- BPE


def test_bpe_agrees_with_the_library(spark):
    lib, own = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), WordBpe(open(VOCABULARY).read())
    rng = random.Random(7)
    texts = ["", "it's WE'LL", "ΣΑΣ ΟΔΟΣ İ", "a<|endoftext|>b<|startoftext|>", "x" * 5000, "漢字 😀 ½Ⅷ", "e\u0301 \u00e9", "\u0000\ufeff\u200b\x85\x1c"]
    texts += ["".join(rng.choice("abth eñ\n'sΣ!?1٣漢  <|>é") for _ in range(120)) for _ in range(150)]
    for t in texts:
        e = lib.encode(t, add_special_tokens=False)
        assert own.encode(t) == e.ids and own.decode(e.ids) == lib.decode(e.ids, skip_special_tokens=False)
    got = {r["doc_id"]: r for r in encode_documents(docs_of(spark, texts), VOCABULARY, with_ids=True).collect()}
    for i, t in enumerate(texts):
        ids = lib.encode(t, add_special_tokens=False).ids
        assert got[i]["ids"] == ids and got[i]["n_tokens"] == len(ids)
        assert got[i]["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()


def test_scan_and_heap_merge_alike():
    own = WordBpe(open(VOCABULARY).read())
    rng = random.Random(8)
    for _ in range(60):
        word = "".join(rng.choice("thaenosir") for _ in range(rng.randint(2, SHORT_WORD + 20)))
        data = word.encode()
        parts = [own.inner[b] for b in data[:-1]] + [own.last[data[-1]]]
        assert own._scan(list(parts)) == own._heap(list(parts))


# --- URLs


def test_urls_by_definition(spark):
    urls = [None, "no scheme", "http://", "http://A.COM", "http://a.com/", "https://x.example.com/en/1?q", "http://www.example.com/en/", "http://sub.www.example.com/en/x", "http://example.com/de", "http://z.net/es/", "http://z.net/fr", "ftp://net/fr/a#b", "http://notnet/es/", "http://com:80/", "http://example.com?/en/", "x://y://z.com/"]
    expect = [None, None, None, None, "com/", "example.com/en/", "www.example.com/en/", "www.example.com/en/", "com/", "net/es/", None, "net/fr/", None, None, None, None]
    rows = judge_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), URL_RULES).orderBy("page_id").collect()
    assert [r["rule"] for r in rows] == expect
    assert [r["verdict"] for r in rows] == ["block" if x in ("example.com/en/", "net/es/", "net/fr/") else "allow" for x in expect]
    assert host_and_path("http://A.b/C?d") == ("a.b", "/C") and judge_urls(spark.createDataFrame([], "page_id long, url string"), URL_RULES).count() == 0


def test_many_rules_broadcast_and_dealt_alike(spark, monkeypatch):
    rng = random.Random(62)
    hosts = sorted({f"{a}.{b}" for a in WORDS[:150] for b in ("com", "org", "net")})
    rules = [(h, rng.choice(["/", "/a/", "/a/b", "/é/"]), rng.choice(["block", "allow"])) for h in hosts] + [("com", "/", "allow"), ("q.com", "/x\u00e9", "block")]
    urls = [None, "none", "http://q.com/x\u00e9y"] + [f"http://{rng.choice(['', 'www.', 'x.y.'])}{rng.choice(hosts + ['other.com', 'other.info'])}{rng.choice(['', '/', '/a/', '/a/b/c', '/é/x', '/z?q'])}" for _ in range(800)]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").repartition(3)
    table = spark.createDataFrame(rules, "host string, path string, verdict string")
    want = []
    for i, u in enumerate(urls):
        host, path = host_and_path(u)
        fits = [(len(h) + len(p), len(h), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=(0, 0, None, "allow"))
        want.append((i, host, path, best[2], best[3]))
    for size in (1 << 20, 1):
        monkeypatch.setattr(urls_module, "MAX_PACKED_BYTES", size)
        monkeypatch.setattr(urls_module, "PART_RULES", 100)
        assert sorted(tuple(r) for r in judge_urls(pages, table).collect()) == want


def test_repeated_vectors_are_queries_and_candidates(spark):
    rows = [(100, [1.0, 0.0]), (100, [1.0, 0.0]), (100, [0.5, 0.5]), (7, [1.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = [tuple(r) for r in exact_top_k(df, df.filter("vec_id = 100"), 10).orderBy("query_no", "rank").select("query_no", "rank", "vec_id", "score").collect()]
    one, half = 1024 * 1024, 1024 * 512
    own = {i: [g[1:] for g in got if g[0] == i] for i in range(3)}
    ranked = [(1, 7, one), (2, 100, one), (3, 100, half)]
    assert sorted(own.values()) == sorted([ranked, ranked, [(1, 7, one), (2, 100, half), (3, 100, half)]])


def test_digest_collisions_do_not_decide():
    index = DigestArray.mapped(DigestArray.pack([(f"h{i}.org", "/", "block") for i in range(50)]))
    index.keys = np.zeros_like(index.keys)  # every probe now meets every rule
    probe = b"h7.org\0/"
    index.keys = np.full_like(index.keys, __import__("xxhash").xxh64_intdigest(probe))
    row = int(index.find([probe])[0])
    assert bytes(index.heap[int(index.starts[row]) : int(index.starts[row + 1])]) == probe
    assert DigestArray.mapped(DigestArray.pack([])).judge(["http://a.com/"], "allow")[3] == ["allow"]


# --- language


def test_viterbi_by_enumeration():
    rng = np.random.default_rng(3)
    lengths = np.array([1, 5, 3, 0, 4])
    scores = rng.normal(0, 3, (lengths.sum(), 3))
    starts = np.cumsum(lengths) - lengths
    path = best_paths(scores, starts, lengths, 2.0)
    for s, n in zip(starts, lengths):
        value = lambda p: sum(scores[s + i, k] for i, k in enumerate(p)) - 2.0 * sum(a != b for a, b in zip(p, p[1:]))
        if n:
            best = max(itertools.product(range(3), repeat=int(n)), key=value)
            assert abs(value(tuple(path[s : s + n])) - value(best)) < 1e-9


def test_mixed_text_gets_spans_and_held_out_rows_their_language(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    held = (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2)
    model = fit(docs.filter(~held))
    test = identify(docs.filter(held).select("doc_id", "text", F.col("lang").alias("truth")), model).toPandas()
    assert (test.truth == test.lang_pred).mean() > 0.95 and test.score.between(0, 1).all()
    texts = {r["lang"]: r["text"] for r in docs.filter("length(text) > 500").select("lang", "text").collect()}
    mixed = spark.createDataFrame([(1, texts["de"][:400] + " " + texts["es"][:400]), (2, "12 34"), (3, None), (4, "привет мир")], "doc_id long, text string")
    out = {r["doc_id"]: r for r in identify(mixed, model).collect()}
    assert {s["lang"] for s in out[1]["spans"]} == {"de", "es"} and len(out[1]["spans"]) <= 3
    assert out[2]["lang_pred"] == out[3]["lang_pred"] == "und" and out[4]["lang_pred"] != "und"
    assert scripts_of(["a", "я", "漢"]).tolist() == [scripts_of([c])[0] for c in "aя漢"]


# --- repeated bytes


def removed_by_definition(texts: list[str | None], length: int) -> list[tuple[int, int, int, str]]:
    data = [(t or "").encode() for t in texts]
    seen = Counter(b[p : p + length] for b in data for p in range(len(b) - length + 1))
    out = []
    for b in data:
        cover = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if seen[b[p : p + length]] > 1:
                cover[p : p + length] = b"\1" * length
        kept = bytes(x for x, c in zip(b, cover) if not c)
        out.append((len(b), sum(cover), sum(cover[i] and not (i and cover[i - 1]) for i in range(len(b))), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("limit", [repeats.SORT_LIMIT, 2])
def test_repeats_by_definition(spark, monkeypatch, limit):
    monkeypatch.setattr(repeats, "SORT_LIMIT", limit)
    rng = random.Random(12)
    passage, long_one = prose(rng, 60), prose(rng, 300)
    texts = [prose(rng, rng.randint(5, 200)) for _ in range(30)]
    texts += [prose(rng, 20) + passage[rng.randint(0, 40) :] + prose(rng, 20) for _ in range(25)]
    texts += [long_one, long_one, long_one[:900] + "#" + long_one[901:], long_one[3:], "ha " * 300, "ab" * 99, "ab" * 101, None, "", passage + passage]
    got = {r["doc_id"]: tuple(r)[1:5] for r in repeats.remove_repeats(docs_of(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == removed_by_definition(texts, 200)


def test_texts_longer_than_a_chunk(spark, monkeypatch):
    monkeypatch.setattr(repeats, "CHUNK", 1 << 10)
    rng = random.Random(13)
    base = prose(rng, 900)
    texts = [base, prose(rng, 100) + base[700:2500] + prose(rng, 200), prose(rng, 800)]
    got = {r["doc_id"]: tuple(r)[1:5] for r in repeats.remove_repeats(docs_of(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == removed_by_definition(texts, 200)


def test_collisions_fall_back_to_bytes(monkeypatch):
    class Blind(repeats.PrefixHash):
        def __call__(self, start, end):
            return super().__call__(start, end) & np.uint64(3)

    monkeypatch.setattr(repeats, "PrefixHash", Blind)
    rng = random.Random(14)
    texts = [bytes(rng.choice(b"ab") for _ in range(30)) for _ in range(12)]
    size = np.full(12, 30)
    data = np.frombuffer(b"".join(texts), np.uint8)
    order, shared = repeats._sorted_with_shared(data, np.arange(12) * 30, size, np.zeros(12, np.int64))
    assert [texts[i] for i in order] == sorted(texts)
    assert shared[1:].tolist() == [next((k for k in range(30) if texts[a][k] != texts[b][k]), 30) for a, b in zip(order, order[1:])]


# --- near duplicates


def components_by_definition(texts: list[str | None], k: int, percent: int) -> list[tuple[int, int]]:
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        n = min(k, len(w))
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set())
    up = list(range(len(texts)))

    def find(x: int) -> int:
        while up[x] != x:
            x = up[x]
        return x

    for i, j in itertools.combinations(range(len(texts)), 2):
        both = len(sets[i] & sets[j])
        if sets[i] and sets[j] and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
            a, b = sorted((find(i), find(j)))
            up[b] = a
    return [(len(s), find(i)) for i, s in enumerate(sets)]


def variants(rng: random.Random) -> list[str | None]:
    out: list[str | None] = []
    shared = prose(rng, 40)
    for _ in range(12):
        base = prose(rng, rng.choice([1, 3, 8, 30, 120, 400])).split()
        for _ in range(rng.randint(1, 7)):
            w = list(base)
            for _ in range(rng.randint(0, max(1, len(w) // 12))):
                w[rng.randrange(len(w))] = rng.choice(WORDS)
            out.append(" ".join(w).upper() if rng.random() < 0.2 else " ".join(w))
    out += [shared + " " + prose(rng, 60) for _ in range(30)] + [None, "", "  ", "one", "one", "ONE"]
    rng.shuffle(out)
    return out


@pytest.mark.parametrize(("k", "block"), [(2, near.BLOCK_MEMBERS), (5, 3)])
def test_near_duplicates_by_definition(spark, monkeypatch, k, block):
    monkeypatch.setattr(near, "BLOCK_MEMBERS", block)
    texts = variants(random.Random(15 + k))
    docs = docs_of(spark, texts)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near.near_duplicates(docs, k).collect()}
    want = components_by_definition(texts, k, 80)
    assert [got[i] for i in range(len(texts))] == want
    kept = {r["doc_id"] for r in near.drop_near_duplicates(docs, k).collect()}
    assert kept == {i for i, (_, c) in enumerate(want) if c == i}


def test_estimates_follow_the_sets():
    rng = np.random.default_rng(16)
    errors = []
    for _ in range(40):
        shared, a, b = (np.unique(rng.integers(0, 2**64, n, dtype=np.uint64)) for n in (700, 150, 90))
        x, y = np.unique(np.concatenate([shared, a])), np.unique(np.concatenate([shared, b]))
        rx, ry = near.registers(x)[None], near.registers(y)[None]
        errors.append(near.estimate(rx, ry, np.array([len(x)]), np.array([len(y)]))[0] - 700 / 940)
        assert (rx != ry).sum() <= 240
    assert abs(np.mean(errors)) < 0.01 and np.std(errors) < 0.04
    assert near.expected_collisions(np.array([500]), np.array([500]))[0] < 1


def test_short_sets_at_the_threshold_share_a_band():
    rng = np.random.default_rng(17)
    for shared, union in ((4, 5), (5, 6), (6, 7), (8, 10), (12, 15)):
        for _ in range(500):
            u = rng.integers(0, 2**64, union, dtype=np.uint64)
            cut = shared + (union - shared) // 2
            a, b = np.sort(u[:cut]), np.sort(np.concatenate([u[:shared], u[cut:]]))
            bands = [near.borrowed(near.registers(x), x).view(np.uint64) for x in (a, b)]
            assert (bands[0] == bands[1]).any()


def test_short_texts_are_linked_like_by_brute_force(spark):
    rng = random.Random(18)
    texts = []
    for _ in range(300):
        w = prose(rng, rng.randint(5, 13)).split()
        texts += [" ".join(w), " ".join([*w, rng.choice(WORDS)])]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near.near_duplicates(docs_of(spark, texts), 2).collect()}
    assert [got[i] for i in range(len(texts))] == components_by_definition(texts, 2, 80)


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(0, 40)] + [(100, 100 + i) for i in range(1, 9)] + [(300, 200)]
    got = {r["node"]: r["label"] for r in near.components(spark.createDataFrame(links, "u long, w long")).collect()}
    rng = random.Random(40)
    for n, m in ((30, 25), (60, 45), (200, 190)):
        edges = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)]
        up = list(range(n))

        def find(x: int) -> int:
            while up[x] != x:
                x = up[x]
            return x

        for u, w in edges:
            a, b = sorted((find(u), find(w)))
            up[b] = a
        found = {r["node"]: r["label"] for r in near.components(spark.createDataFrame(edges, "u long, w long")).collect()}
        assert found == {x: find(x) for e in edges if e[0] != e[1] for x in e}
    assert all(got[i] == 0 for i in range(41)) and all(got[100 + i] == 100 for i in range(9)) and got[200] == got[300] == 200


def test_repeated_ids_are_one_document(spark):
    a, b = prose(random.Random(50), 60), prose(random.Random(51), 60)
    rows = [(1, a), (1, b), (2, a + " x"), (3, b + " y"), (9, None), (None, prose(random.Random(52), 60))]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    got = sorted(tuple(r) for r in near.near_duplicates(docs).collect() if r["doc_id"] is not None)
    assert got == [(1, 56, 1, True), (1, 56, 1, True), (2, 57, 1, False), (3, 57, 1, False), (9, 0, 9, True)]
    (alone,) = [tuple(r) for r in near.near_duplicates(docs).collect() if r["doc_id"] is None]
    assert alone == (None, 56, None, True)


def test_one_row_of_a_group_stays(spark):
    a, b = prose(random.Random(53), 60), prose(random.Random(54), 60)
    rows = [(1, a), (1, a), (2, a + " x"), (None, b), (None, b), (7, ""), (7, ""), (8, None), (4, b + " z")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    assert sorted(r["doc_id"] for r in near.drop_near_duplicates(docs).collect()) == [1, 4, 7, 7, 8]
    named = docs.withColumnRenamed("doc_id", "D").select(F.col("D").cast("string").alias("doc_id"), "text", F.lit(1).alias("R1"), F.lit(2).alias("r2"), F.lit(3).alias("node"))
    out = near.drop_near_duplicates(named)
    assert out.columns == ["doc_id", "text", "R1", "r2", "node"] and sorted(r["doc_id"] for r in out.collect()) == ["1", "4", "7", "7", "8"]


def test_a_hot_bucket_of_texts_of_many_sizes(spark, monkeypatch):
    monkeypatch.setattr(near, "BLOCK_MEMBERS", 4)
    rng = random.Random(55)
    words = prose(rng, 400).split()
    texts = [" ".join(words[: rng.randint(8, 400)]) for _ in range(60)]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near.near_duplicates(docs_of(spark, texts), 2).collect()}
    assert [got[i] for i in range(len(texts))] == components_by_definition(texts, 2, 80)


# --- what awkward rows get


def by_id(df, *columns):
    out = defaultdict(list)
    for r in df.collect():
        out[r["doc_id"]].append(tuple(r[c] for c in columns))
    return dict(out)


def test_awkward_rows_have_defined_results(spark):
    docs = edge_docs(spark)
    words = {0: 7, 1: 7, 2: 0, 3: 0, 4: 0, None: 5, 5: 3000, 6: 6}
    assert by_id(judge_quality(docs), "n_words", "base_failed", "kept") == {i: [(n, True, False)] * (1 + (i == 1)) for i, n in words.items()}
    assert keep_good(docs).count() == 0
    near_ = by_id(near.near_duplicates(docs), "n_shingles", "component_id", "kept")
    assert near_ == {0: [(3, 0, True)], 1: [(3, 0, False)] * 2, 2: [(0, 2, True)], 3: [(0, 3, True)], 4: [(0, 4, True)], None: [(1, None, True)], 5: [(1, 5, True)], 6: [(2, 6, True)]}
    assert sorted(str(r["doc_id"]) for r in near.drop_near_duplicates(docs).collect()) == ["0", "2", "3", "4", "5", "6", "None"]
    size = {i: len((t or "").encode()) for i, t, *_ in EDGE}
    gone = by_id(repeats.remove_repeats(docs), "n_bytes", "n_removed", "n_spans")
    assert gone == {i: [(size[i], size[i] * (i == 5), int(i == 5))] * (1 + (i == 1)) for i in size}
    lines = by_id(drop_recurring_lines(docs), "text", "n_lines", "n_dropped")
    assert lines == {i: [(t, len(t.split("\n")) if t is not None else 0, 0)] * (1 + (i == 1)) for i, t, *_ in EDGE}
    low = by_id(drop_recurring_lines(docs, min_docs=2), "n_dropped")
    assert low[0] == [(0,)] and low[1] == [(3,), (3,)] and all(v == [(0,)] for i, v in low.items() if i not in (0, 1))
    taken = Counter(r["doc_id"] for r in mix_index(docs, max_repetition=2.0).collect())
    assert all(taken[i] >= 1 + (i == 1) for i in size)
    assert by_id(encode_documents(docs, VOCABULARY), "n_tokens")[2] == by_id(encode_documents(docs, VOCABULARY), "n_tokens")[3] == [(0,)]
