"""Quality rules by compression bands.

A text's zstandard ratio (compressed bytes over bytes) is low where it repeats itself and high where it is noise. Both
the whole document and its fixed chunks are compressed; limits depend on the length, since short texts compress worse.
The chunks cover every byte: a last part too short for the chunk band has the band of whole texts of its length, and one
for which that sets no limit belongs to the chunk before. A document fails when its whole ratio leaves the band of its length, or when too many of its bytes lie in chunks
outside the chunk band. Chunks find long repetitive parts of documents whose other parts are sound.

Null and empty texts have no words and fail the base rules. Every count is over the whole text.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_function

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"


@dataclass(frozen=True)
class Bands:
    """(least bytes, lowest ratio, highest ratio), by ascending length; the last row whose length is reached holds."""

    whole: tuple[tuple[int, float, float], ...] = ((0, 0.0, 9.0), (200, 0.30, 1.0), (400, 0.25, 0.90), (800, 0.22, 0.80), (1600, 0.20, 0.72), (6400, 0.16, 0.70), (25_600, 0.14, 0.70))
    chunk_bytes: int = 4096
    least_chunk: int = 2048
    chunk: tuple[float, float] = (0.16, 0.74)
    most_bad: float = 0.25
    level: int = 3


def base_counts(text: str) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    words = text.encode("utf-8", "surrogatepass").split()
    n = len(words)
    word_chars = len(text) - sum(map(text.count, BLANKS))
    symbols = sum(map(text.count, SYMBOLS))
    lines = [x for x in text.split("\n") if x.strip(BLANKS)]
    repeated = 0
    if n >= 4:
        windows = list(zip(words, words[1:], words[2:]))
        if len(set(windows)) < len(windows):
            seen = Counter(windows)
            end = 0
            for k, w in enumerate(windows):
                if seen[w] > 1:
                    repeated += k + 3 - max(k, end)
                    end = k + 3
    return n, word_chars, symbols, len(lines) - len(set(lines)), repeated


class Judge:
    def __init__(self, bands: Bands):
        self.bands, self.zstd = bands, zstandard.ZstdCompressor(level=bands.level)

    def ratio(self, data) -> float:
        return len(self.zstd.compress(data)) / len(data)

    def whole_band(self, n: int) -> tuple[float, float]:
        return next((lo, hi) for least, lo, hi in reversed(self.bands.whole) if n >= least)

    def parts(self, n: int) -> list[tuple[int, int]]:
        """(start, end) of the chunks of n bytes, which cover them all."""
        b = self.bands
        starts = list(range(0, n, b.chunk_bytes))
        if len(starts) > 1 and n - starts[-1] < min(b.whole[1][0], b.least_chunk):
            starts.pop()
        return list(zip(starts, [*starts[1:], n]))

    def verdict(self, text: str) -> tuple[float | None, float, str]:
        """The whole ratio, the share of bytes in bad chunks, and why the text fails ('' if it doesn't)."""
        data, b = text.encode("utf-8", "surrogatepass"), self.bands
        if not data:
            return None, 0.0, ""
        whole = self.ratio(data)
        low, high = self.whole_band(len(data))
        view, bad = memoryview(data), {"repetitive": 0, "incompressible": 0}
        for at, end in self.parts(len(data)):
            n = end - at
            least, most = b.chunk if n >= b.least_chunk else self.whole_band(n)
            r = whole if n == len(data) else self.ratio(view[at:end])
            if r < least:
                bad["repetitive"] += n
            elif r > most:
                bad["incompressible"] += n
        share = sum(bad.values()) / len(data)
        if whole < low:
            why = "repetitive"
        elif whole > high:
            why = "incompressible"
        elif share > b.most_bad:
            why = f"{max(bad, key=bad.get)} chunks"
        else:
            why = ""
        return whole, share, why


def rules_column(bands: Bands = Bands()):
    """A column function text -> struct of the counts, the ratios and the verdict."""

    def make():
        judge = Judge(bands)

        def one(text: str) -> dict:
            n, chars, symbols, dup, rep = base_counts(text)
            failed = n < 50 or 100 * rep > 50 * n
            ratio, share, why = judge.verdict(text)
            return {"n_words": n, "word_chars": chars, "n_symbols": symbols, "n_dup_lines": dup, "n_repeat_words": rep, "base_failed": failed, "kept": not failed and not why, "ratio": ratio, "bad_chunk_share": share, "reason": "base" if failed else why}

        return lambda texts: [one(x) for x in texts]

    return text_function(make, "n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean, ratio double, bad_chunk_share double, reason string")


def quality_rules(docs: DataFrame, *, bands: Bands = Bands(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row with counts and verdict; other columns of docs are not read."""
    return docs.select(F.col(id_col), rules_column(bands)(F.col(text_col)).alias("_r")).select(id_col, "_r.*")
