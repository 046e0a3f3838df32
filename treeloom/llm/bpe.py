"""BPE encoding and decoding with a contiguous rank array per word.

A word is held as its parts in order, with one rank for each adjacent pair beside them.  Encoding scans the
ranks for the minimum, deletes that boundary and refreshes the two neighbouring ranks, until no pair has a
rank.  The scan is quadratic in the parts of a word, so it serves words of up to ``SHORT_WORD`` parts; longer
ones take the same merges in the same order from a heap.

Null texts count as empty: no token, empty decoding.  Repeated rows are encoded alike.  Texts may be of any
length; memory is bounded by one Arrow batch and a word cache of ``CACHE_WORDS`` entries, half of them new ones and
half those of the time before, so that frequent words stay.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from treeloom.llm.store import lean

SHORT_WORD = 64
CACHE_WORDS = 100_000
CACHE_WORD_CHARS = 64
NO_RANK = 1 << 60

#: White space as Unicode defines it (fixed values).
SPACES = r"\t-\r \x85\xa0  -     　"


def byte_symbols() -> list[str]:
    """The visible character that stands for each byte: printable Latin-1 for itself, the rest from 256 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class WordBpe:
    """Encoder and decoder for one vocabulary file with word-end suffixes and byte symbols.

    ``spec`` is the JSON text of the file.  Special tokens in a text are recognised in the raw text and the
    stretches between them are normalised one by one, as the public library does by default.
    """

    def __init__(self, spec: str):
        conf = json.loads(spec)
        model = conf["model"]
        self.vocab: dict[str, int] = model["vocab"]
        suffix = model["end_of_word_suffix"] or ""
        self.tokens = {i: t for t, i in self.vocab.items()}
        self.specials = {t["content"]: t["id"] for t in conf["added_tokens"]}
        self.tokens |= {i: t for t, i in self.specials.items()}
        self.pairs: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.pairs[self.vocab[a], self.vocab[b]] = (rank, self.vocab[a + b])
        symbols = byte_symbols()
        self.inner = [self.vocab[s] for s in symbols]
        self.last = [self.vocab[s + suffix] for s in symbols]
        self.cache: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}
        self._special = regex.compile("|".join(map(regex.escape, sorted(self.specials, key=len, reverse=True)))) if self.specials else None
        self._spaces = regex.compile(f"[{SPACES}]+")
        self._words = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|\p{{L}}+|\p{{N}}|[^{SPACES}\p{{L}}\p{{N}}]+")

    def normalise(self, text: str) -> str:
        text = self._spaces.sub(" ", unicodedata.normalize("NFC", text))
        # lower case is taken letter by letter: a capital sigma has one lower form wherever it stands
        return text.replace("Σ", "σ").lower()

    def merge(self, word: str) -> tuple[int, ...]:
        data = word.encode()
        parts = [self.inner[b] for b in data[:-1]] + [self.last[data[-1]]]
        return tuple(self._scan(parts) if len(parts) <= SHORT_WORD else self._heap(parts))

    def _scan(self, parts: list[int]) -> list[int]:
        find = self.pairs.get
        none = (NO_RANK, -1)
        # ranks[i] belongs to the boundary between part i and part i + 1
        ranks = [find(p, none)[0] for p in zip(parts, parts[1:])]
        while ranks:
            least = min(ranks)
            if least == NO_RANK:
                break
            i = ranks.index(least)
            parts[i] = self.pairs[parts[i], parts[i + 1]][1]
            del parts[i + 1], ranks[i]
            if i:
                ranks[i - 1] = find((parts[i - 1], parts[i]), none)[0]
            if i < len(ranks):
                ranks[i] = find((parts[i], parts[i + 1]), none)[0]
        return parts

    def _heap(self, parts: list[int]) -> list[int]:
        n = len(parts)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        queue = [(r[0], i, p[0], p[1]) for i, p in enumerate(zip(parts, parts[1:])) if (r := self.pairs.get(p))]
        heapq.heapify(queue)
        while queue:
            _, i, a, b = heapq.heappop(queue)
            j = after[i] if parts[i] == a else n
            if j >= n or parts[j] != b:
                continue
            parts[i], parts[j] = self.pairs[a, b][1], -1
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y < n and (r := self.pairs.get((parts[x], parts[y]))):
                    heapq.heappush(queue, (r[0], x, parts[x], parts[y]))
        return [p for p in parts if p >= 0]

    def _plain(self, text: str, ids: list[int]) -> None:
        cache = self.cache
        for word in self._words.findall(self.normalise(text)):
            got = cache.get(word)
            if got is None:
                got = self.older.get(word)
                if got is None:
                    got = self.merge(word)
                if len(word) <= CACHE_WORD_CHARS:
                    if len(cache) >= CACHE_WORDS // 2:
                        self.older, self.cache = cache, {}
                        cache = self.cache
                    cache[word] = got
            ids += got

    def encode(self, text: str | None) -> list[int]:
        ids: list[int] = []
        if not text:
            return ids
        at = 0
        if self._special is not None:
            for m in self._special.finditer(text):
                self._plain(text[at : m.start()], ids)
                ids.append(self.specials[m[0]])
                at = m.end()
        self._plain(text[at:] if at else text, ids)
        return ids

    def decode(self, ids: list[int]) -> str:
        """Tokens joined by one blank: the file names no decoder, so word ends and byte symbols stay."""
        return " ".join(map(self.tokens.__getitem__, ids))


def encode_documents(docs: DataFrame, spec_path: str, with_ids: bool = False) -> DataFrame:
    """Encodes and decodes every ``text`` of ``docs(doc_id, text)``.

    Returns doc_id, n_tokens, ids_sha256, decoded_sha256 and, if asked for, the ids themselves.  The vocabulary
    file is read on the driver and broadcast (its size is fixed, a few MB).
    """
    with open(spec_path, encoding="utf-8") as f:
        spec = docs.sparkSession.sparkContext.broadcast(f.read())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = WordBpe(spec.value)
        names = {i: str(i) for i in bpe.tokens}
        for batch in batches:
            n, h, d, all_ids = [], [], [], []
            for text in batch.column("text"):
                ids = bpe.encode(text.as_py())
                n.append(len(ids))
                h.append(hashlib.sha256(" ".join(map(names.__getitem__, ids)).encode()).hexdigest())
                d.append(hashlib.sha256(bpe.decode(ids).encode()).hexdigest())
                if with_ids:
                    all_ids.append(ids)
            out = {"doc_id": batch.column("doc_id"), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(h, pa.string()), "decoded_sha256": pa.array(d, pa.string())}
            if with_ids:
                out["ids"] = pa.array(all_ids, pa.list_(pa.int32()))
            yield pa.RecordBatch.from_pydict(out)

    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string"
    return docs.select("doc_id", "text").mapInArrow(lean(run), schema + (", ids array<int>" if with_ids else ""))
