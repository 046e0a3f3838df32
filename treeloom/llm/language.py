"""Language identification of mixed text: script ranges, per-word scores, and a Viterbi path over words.

Words are runs of letters.  The script of a word's first letter narrows the candidate languages to those that use the
script in training.  A word's score for a language is the log probability of its character 1- to 3-grams (hashed into
``BUCKETS``), learned with additive smoothing.  Over the words of a text the best path is found where every change of
language costs ``PENALTY``; its runs are the labelled spans.  The text's language is the one with most letters, and
the score is its share of them.

Training takes at most about ``fit_rows`` labelled rows, chosen by the hash of their id; this bound is a parameter.  The
model has one row a language.  Texts that are null or have no letter are ``und`` with score 0 and no span, and so is
every text if nothing was learned.  Repeated rows get one answer.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BUCKETS = 1 << 16
FIT_ROWS = 20_000
PENALTY = 12.0
SMOOTHING = 0.5
#: A language uses a script that at least this share of its training letters' words begin with.
SCRIPT_SHARE = 0.01
CHUNK_WORDS = 1_000_000

#: First code points of script ranges and the script from there on (fixed values).
SCRIPT_RANGES = [
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"),
    (0x0900, "devanagari"), (0x0980, "bengali"), (0x0A00, "gurmukhi"), (0x0A80, "gujarati"), (0x0B00, "oriya"), (0x0B80, "tamil"),
    (0x0C00, "telugu"), (0x0C80, "kannada"), (0x0D00, "malayalam"), (0x0D80, "sinhala"), (0x0E00, "thai"), (0x0E80, "lao"),
    (0x0F00, "tibetan"), (0x1000, "burmese"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "ethiopic"), (0x1380, "other"),
    (0x1780, "khmer"), (0x1800, "mongolian"), (0x1880, "other"), (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"),
    (0x3040, "kana"), (0x3100, "other"), (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "latin"), (0xFB50, "arabic"), (0xFE00, "other"),
]
SCRIPTS = sorted({s for _, s in SCRIPT_RANGES})
_EDGES = np.array([a for a, _ in SCRIPT_RANGES])
_SCRIPT_OF = np.array([SCRIPTS.index(s) for _, s in SCRIPT_RANGES])
_LETTERS = regex.compile(r"\p{L}+")
_BREAK = 10


def words_of(text: str | None) -> list[str]:
    return _LETTERS.findall(text.lower()) if text else []


def scripts_of(words: list[str]) -> np.ndarray:
    first = np.fromiter((ord(w[0]) for w in words), np.int64, len(words))
    return _SCRIPT_OF[np.searchsorted(_EDGES, first, "right") - 1]


def gram_buckets(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, word number) of every 1- to 3-gram, word edges included in the longer ones."""
    cp = np.frombuffer(("\n" + "\n".join(words) + "\n").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    edge = cp == _BREAK
    word = np.cumsum(edge) - 1
    buckets, owners = [], []
    h = np.zeros(len(cp), np.uint64)
    for n in (1, 2, 3):
        h = h[: len(cp) - n + 1] * np.uint64(0x9E3779B97F4A7C15) + cp[n - 1 :] + np.uint64(n)
        fine = ~edge if n == 1 else np.ones(len(h), bool) if n == 2 else ~edge[1:-1]
        x = h[fine]
        x = (x ^ (x >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93)
        buckets.append((x >> np.uint64(48)).astype(np.int64) % BUCKETS)
        owners.append(word[: len(h)][fine])
    return np.concatenate(buckets), np.concatenate(owners)


@dataclass
class Model:
    languages: list[str]
    log_p: np.ndarray  # bucket, language
    allowed: np.ndarray  # script, language

    def word_scores(self, words: list[str]) -> np.ndarray:
        bucket, owner = gram_buckets(words)
        out = np.empty((len(words), len(self.languages)))
        for j in range(len(self.languages)):
            out[:, j] = np.bincount(owner, self.log_p[bucket, j], len(words))
        allowed = self.allowed[scripts_of(words)]
        return np.where(allowed | ~allowed.any(axis=1, keepdims=True), out, -1e6)


def best_paths(scores: np.ndarray, starts: np.ndarray, lengths: np.ndarray, penalty: float) -> np.ndarray:
    """Best language of every word; the texts' words lie one after another. All texts advance a word at a time."""
    by = np.argsort(-lengths, kind="stable")
    starts, lengths = starts[by], lengths[by]
    longest, kinds = int(lengths.max(initial=0)), scores.shape[1]
    path = np.zeros(len(scores), np.int32)
    if kinds < 2 or not longest:
        return path
    active = np.searchsorted(-lengths, -np.arange(longest), "left")  # texts longer than t
    value = scores[starts[: active[0]]].copy()
    offsets = np.concatenate([[0], np.cumsum(active)])
    back = np.empty((offsets[-1], kinds), np.int16 if kinds < 1 << 15 else np.int32)
    own = np.arange(kinds)
    final = np.zeros(len(starts), np.int32)
    for t in range(1, longest):
        a = active[t]
        if a < len(value):
            final[a : len(value)] = value[a:].argmax(axis=1)
            value = value[:a]
        top = value.argmax(axis=1)
        change = value[np.arange(a), top][:, None] - penalty
        stay = value >= change
        back[offsets[t] : offsets[t + 1]] = np.where(stay, own, top[:, None])
        value = np.where(stay, value, change) + scores[starts[:a] + t]
    final[: len(value)] = value.argmax(axis=1)
    state = final.copy()
    for t in range(longest - 1, -1, -1):
        a = active[t]
        path[starts[:a] + t] = state[:a]
        if t:
            state[:a] = back[offsets[t] + np.arange(a), state[:a]]
    return path


def spans_of(model: Model, texts: list[list[str]], penalty: float) -> list[tuple[str, float, list[tuple[int, int, str]]]]:
    """(language, score, spans of (first word, last word, language)) of texts given as words."""
    number: dict[str, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for t in texts for w in t), np.int64)
    if not len(ids) or not model.languages:
        return [("und", 0.0, [])] * len(texts)
    unique = list(number)
    letters = np.fromiter(map(len, unique), np.int64, len(unique))[ids]
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    starts = np.cumsum(lengths) - lengths
    path = best_paths(model.word_scores(unique)[ids], starts, lengths, penalty)
    owner = np.repeat(np.arange(len(texts)), lengths)
    kinds = len(model.languages)
    mass = np.bincount(owner * kinds + path, letters, len(texts) * kinds).reshape(-1, kinds)
    head = np.nonzero(np.append(True, (owner[1:] != owner[:-1]) | (path[1:] != path[:-1])))[0]
    tail = np.append(head[1:], len(path)) - 1
    spans: list[list[tuple[int, int, str]]] = [[] for _ in texts]
    for a, b in zip(head.tolist(), tail.tolist()):
        o = owner[a]
        spans[o].append((a - int(starts[o]), b - int(starts[o]), model.languages[path[a]]))
    best, total = mass.argmax(axis=1), mass.sum(axis=1)
    return [(model.languages[k], float(mass[i, k] / total[i]), spans[i]) if total[i] else ("und", 0.0, []) for i, k in enumerate(best)]


def fit(labelled: DataFrame, fit_rows: int = FIT_ROWS) -> Model:
    """Learns from ``labelled(doc_id, text, lang)``; counts are summed on the executors, one model row a language comes back."""
    labelled = labelled.filter("lang is not null and text is not null").select("doc_id", "text", "lang")
    total = labelled.count()
    if total > fit_rows:
        labelled = labelled.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(fit_rows / total * (1 << 30)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, np.ndarray] = {}
        for batch in batches:
            by: dict[str, list[str]] = {}
            for text, lang in zip(batch.column("text").to_pylist(), batch.column("lang").to_pylist()):
                by.setdefault(lang, []).extend(words_of(text))
            for lang, words in by.items():
                if not words:
                    continue
                counts = seen.setdefault(lang, np.zeros(BUCKETS + len(SCRIPTS), np.int64))
                counts[:BUCKETS] += np.bincount(gram_buckets(words)[0], minlength=BUCKETS)
                counts[BUCKETS:] += np.bincount(scripts_of(words), minlength=len(SCRIPTS))
        for lang, counts in seen.items():
            at = np.nonzero(counts)[0]
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(counts[at])], ["lang", "feature", "n"])

    table = labelled.mapInArrow(run, "lang string, feature int, n long").groupBy("lang", "feature").agg(F.sum("n").alias("n")).toArrow()
    languages = sorted(set(table.column("lang").to_pylist()))
    counts = np.zeros((BUCKETS + len(SCRIPTS), len(languages)))
    if languages:
        at = {x: i for i, x in enumerate(languages)}
        counts[table.column("feature").to_numpy(), [at[x] for x in table.column("lang").to_pylist()]] = table.column("n").to_numpy()
    grams, scripts = counts[:BUCKETS] + SMOOTHING, counts[BUCKETS:]
    log_p = np.log(grams / grams.sum(axis=0))
    return Model(languages, log_p.astype(np.float32), scripts >= SCRIPT_SHARE * np.maximum(scripts.sum(axis=0), 1))


def identify(docs: DataFrame, model: Model, penalty: float = PENALTY) -> DataFrame:
    """lang_pred, score and spans (first word, last word, language) beside all other columns of ``docs`` but text."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    others = [c for c in docs.columns if c not in ("text", "lang_pred", "score", "spans")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple[str, float, list]] = []
            pending: list[list[str]] = []
            size = 0
            for text in batch.column("text"):
                pending.append(words_of(text.as_py()))
                size += len(pending[-1])
                if size >= CHUNK_WORDS:
                    out += spans_of(held.value, pending, penalty)
                    pending, size = [], 0
            out += spans_of(held.value, pending, penalty)
            lang, score, spans = zip(*out) if out else ((), (), ())
            kind = pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32()), ("lang", pa.string())]))
            made = [pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array([[dict(zip(("first", "last", "lang"), s)) for s in x] for x in spans], kind)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in others), *made], [*others, "lang_pred", "score", "spans"])

    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in others)
    return docs.select(*[F.col(f"`{c}`") for c in others], "text").mapInArrow(run, schema + ", lang_pred string, score double, spans array<struct<first:int,last:int,lang:string>>")
