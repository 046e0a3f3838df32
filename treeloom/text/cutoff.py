"""Index or scan for a text pattern: the number of occurrences from which on scanning all texts is sooner."""

from __future__ import annotations


def cut_off(text_bytes: int, sample: int) -> int:
    """Occurrences above which scanning all texts beats locating them; linear in the text, rarer samples cost more."""
    return max(1, text_bytes * 4 // (sample * 125)) if sample > 4 else max(1, text_bytes // 150)


def text_path(occurrences: int, text_bytes: int, sample: int) -> str:
    """"index" or "scan" for a pattern of so many occurrences."""
    return "index" if occurrences < cut_off(text_bytes, sample) else "scan"


def calibrated(ladder: list[tuple[int, float, float]]) -> float | None:
    """The occurrences at which the index costs what a scan costs, from measured (occurrences, index ms, scan ms).

    The index costs a fixed part and a part for each occurrence (least squares), the scan the mean of its times; None if the index
    does not grow with the occurrences."""
    n = len(ladder)
    if n < 2:
        return None
    x, y, scan = ([float(r[i]) for r in ladder] for i in range(3))
    mx, my = sum(x) / n, sum(y) / n
    spread = sum((a - mx) ** 2 for a in x)
    slope = sum((a - mx) * (b - my) for a, b in zip(x, y)) / spread if spread else 0.0
    return None if slope <= 0 else max(0.0, (sum(scan) / n - (my - slope * mx)) / slope)
