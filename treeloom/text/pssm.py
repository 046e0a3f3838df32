"""Scoring matrices over texts: a text matches if some window scores more than a threshold."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

Matrix = list[dict[str, int]]
#: Position frequency matrices of lengths 8, 12 and 14 on ACGT, and thresholds on the scaled scores (own values).
FREQUENCIES = {
    "M1": [(9, 1, 3, 2), (2, 8, 1, 4), (1, 2, 9, 3), (7, 3, 2, 3), (2, 2, 3, 8), (3, 7, 2, 3), (6, 2, 4, 3), (1, 4, 8, 2)],
    "M2": [(9, 1, 3, 2), (2, 8, 1, 4), (1, 2, 9, 3), (7, 3, 2, 3), (2, 2, 3, 8), (3, 7, 2, 3), (6, 2, 4, 3), (1, 4, 8, 2), (5, 5, 3, 2), (2, 9, 2, 2), (3, 3, 6, 3), (8, 2, 2, 3)],
    "M3": [(9, 1, 3, 2), (2, 8, 1, 4), (1, 2, 9, 3), (7, 3, 2, 3), (2, 2, 3, 8), (3, 7, 2, 3), (6, 2, 4, 3), (1, 4, 8, 2), (5, 5, 3, 2), (2, 9, 2, 2), (3, 3, 6, 3), (8, 2, 2, 3), (2, 3, 3, 7), (4, 6, 3, 2)],
}
THRESHOLDS = {"M1": 5500, "M2": 6500, "M3": 7500}
ALPHABET = "ACGT"


def log_odds(frequencies: list[tuple[int, ...]], background: dict[str, float] | None = None, pseudo: float = 1.0, scale: int = 1000) -> Matrix:
    """Integer weights: scaled log2 of (count plus pseudo-count, normalised) over the background."""
    back = background or {c: 1 / len(ALPHABET) for c in ALPHABET}
    out: Matrix = []
    for column in frequencies:
        total = sum(column) + pseudo * len(ALPHABET)
        out.append({c: round(scale * math.log2((n + pseudo) / total / back[c])) for c, n in zip(ALPHABET, column)})
    return out


def score(weights: Matrix, window: str) -> int:
    return sum(w[c] for w, c in zip(weights, window))


def best_scores(values: list[str | None], weights: Matrix) -> list[int | None]:
    """Best window of each text; null for a text shorter than the matrix. Symbols outside the matrix never match."""
    table = np.full((len(weights), 256), -(10**9), np.int64)
    for k, w in enumerate(weights):
        for c, x in w.items():
            table[k, ord(c)] = x
    out: list[int | None] = []
    for v in values:
        data = np.frombuffer((v or "").encode(), np.uint8)
        if len(data) < len(weights):
            out.append(None)
            continue
        n = len(data) - len(weights) + 1
        total = np.zeros(n, np.int64)
        for k in range(len(weights)):
            total += table[k][data[k : k + n]]
        out.append(int(total.max()))
    return out


def matches(texts: DataFrame, weights: Matrix, threshold: int) -> DataFrame:
    """The rows of ``texts`` whose ``value`` has a window that scores more than ``threshold``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            best = best_scores(batch.column("value").to_pylist(), weights)
            yield batch.filter(pa.array([b is not None and b > threshold for b in best], pa.bool_()))

    return texts.mapInArrow(run, texts.schema)
