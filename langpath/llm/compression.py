"""Quality rules with compression bands.

Base rules count words, symbols, repeated lines and repeated 8-word windows.  The bands then
look at zstandard ratios (raw bytes / compressed bytes) of the whole document and of fixed chunks of
it: text that compresses far better than prose is repetitive, text that compresses far worse is
noise.  Short texts compress less well whatever they say, so every limit depends on the length
of what is compressed.

Defined cases: a null text is empty (fails the base rule of 20 words); empty texts have ratio 0 and no
chunks; repeated rows get equal verdicts; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

# Fixed values of the base rules.
SYMBOLS = b"#*$%&|<>"
WINDOW = 8


@dataclass(frozen=True)
class Bands:
    """Limits by length: (bytes at least, lowest ratio, highest ratio), longest last."""

    # lowest ratios: below the least of good prose of each length, above base64 (1.09 to 1.33) and, from 1 KB on, words of random letters (1.60 to 1.72)
    whole: tuple[tuple[int, float, float], ...] = ((0, 0.55, 2.6), (256, 1.15, 3.2), (512, 1.35, 3.2), (1024, 1.66, 4.0), (2048, 1.75, 4.0), (4096, 1.85, 5.0), (16384, 1.9, 6.5), (65536, 1.9, 8.0))
    chunk_bytes: int = 4096
    chunk: tuple[tuple[int, float, float], ...] = ((0, 0.55, 2.6), (256, 1.15, 3.2), (512, 1.35, 3.2), (1024, 1.66, 4.0), (2048, 1.75, 4.0), (4096, 1.85, 5.0))
    bad_chunks: float = 0.3  # share of a document's chunks that may lie outside
    level: int = 3


def _limits(table: tuple[tuple[int, float, float], ...], size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    k = np.searchsorted(np.array([t[0] for t in table]), size, side="right") - 1
    return np.array([t[1] for t in table])[k], np.array([t[2] for t in table])[k]


def repeated_in_windows(codes: np.ndarray, first: np.ndarray, width: int = WINDOW) -> np.ndarray:
    """Per text: words that lie in a ``width``-word window found twice or more in it.

    Windows are named exactly, by pairing the names of their halves."""
    n, texts = len(codes), len(first) - 1
    owner = np.repeat(np.arange(texts), np.diff(first))
    name, span = codes.astype(np.int64), 1
    while span < width:
        nxt = np.zeros(n, np.int64)
        if n > span:
            nxt[: n - span] = name[span:]
        top = int(nxt.max(initial=0)) + 1
        name = _rank(name * top + nxt)
        span *= 2
    whole = np.zeros(n, bool)
    at = np.arange(n)
    whole[: max(n - width + 1, 0)] = True
    if n:
        whole &= at + width <= first[1:][owner]
    key = _rank(name * (texts + 1) + owner)[whole]
    if not len(key):
        return np.zeros(texts, np.int64)
    twice = np.bincount(key)[key] > 1
    delta = np.zeros(n + 1, np.int64)
    hit = at[whole][twice]
    np.add.at(delta, hit, 1)
    np.add.at(delta, hit + width, -1)
    covered = np.cumsum(delta)[:n] > 0
    return np.bincount(owner[covered], minlength=texts).astype(np.int64)


def _rank(x: np.ndarray) -> np.ndarray:
    import pandas as pd

    return pd.factorize(x)[0].astype(np.int64)


def duplicate_lines(text: bytes) -> int:
    """Lines with a word that equal an earlier line."""
    if b"\n" not in text:
        return 0
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    return len(lines) - len(set(lines))


def ratios(text: bytes, pack: zstandard.ZstdCompressor, chunk: int) -> tuple[float, list[tuple[int, float]]]:
    if not text:
        return 0.0, []
    whole = len(text) / len(pack.compress(text))
    if len(text) <= chunk:
        return whole, [(len(text), whole)]
    cuts = [text[a : a + chunk] for a in range(0, len(text), chunk)]
    if len(cuts[-1]) < chunk // 2:  # a short rest is judged with what stands before it
        cuts[-1] = text[-chunk:]
    return whole, [(len(c), len(c) / len(pack.compress(c))) for c in cuts]


SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_bytes long, ratio double, n_chunks long, n_low_chunks long, n_high_chunks long, verdict string"


def score(docs: DataFrame, bands: Bands = Bands(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Base counts, ratios and verdict of each document.  No shuffle."""
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    marks = np.zeros(256, bool)
    marks[list(SYMBOLS)] = True

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=bands.level)
        for batch in common.slices(batches, "text"):
            raw, off = common.flat_text(batch.column("text"))
            start, end, h, first = common.words_of(raw, off)
            n_words = np.diff(first)
            lead = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
            chars = np.concatenate([[0], np.cumsum(lead[end] - lead[start])])
            signs = np.concatenate([[0], np.cumsum(marks[raw])])
            repeat = repeated_in_windows(_rank(h), first)
            blob = raw.tobytes()
            dup, whole, n_chunks, low, high = [], [], [], [], []
            for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True):
                doc = blob[a:b]
                dup.append(duplicate_lines(doc))
                r, parts = ratios(doc, pack, bands.chunk_bytes)
                whole.append(r)
                n_chunks.append(len(parts))
                if parts:
                    size, part = np.array(parts).T
                    lo, hi = _limits(bands.chunk, size)
                    low.append(int((part < lo).sum()))
                    high.append(int((part > hi).sum()))
                else:
                    low.append(0)
                    high.append(0)
            size, whole, n_chunks, low, high = np.diff(off), np.array(whole, float), np.array(n_chunks, np.int64), np.array(low, np.int64), np.array(high, np.int64)
            lo, hi = _limits(bands.whole, size)
            base = (n_words < 20) | (100 * repeat > 30 * n_words)
            verdict = np.full(len(size), "kept", object)
            verdict[low > bands.bad_chunks * n_chunks] = "noisy chunks"
            verdict[high > bands.bad_chunks * n_chunks] = "repetitive chunks"
            verdict[(size > 0) & (whole < lo)] = "incompressible"
            verdict[whole > hi] = "repetitive"
            verdict[base] = "base"
            cols = [batch.column("doc_id"), n_words, chars[first[1:]] - chars[first[:-1]], signs[off[1:]] - signs[off[:-1]], np.array(dup, np.int64), repeat, base, verdict == "kept", size, whole, n_chunks, low, high, verdict]
            kinds = [None, *[pa.int64()] * 5, pa.bool_(), pa.bool_(), pa.int64(), pa.float64(), *[pa.int64()] * 3, pa.string()]
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    return src.mapInArrow(run, SCHEMA)


def keep(docs: DataFrame, bands: Bands = Bands(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents that pass, with all their columns; one scan and no shuffle."""
    schema, where = docs.schema, docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, text):
            yield batch.filter(judge(batch.column(where), bands))

    return docs.mapInArrow(run, schema)


def judge(column: pa.Array, bands: Bands = Bands()) -> pa.Array:
    """Verdict (kept or not) of each text of an Arrow column."""
    raw, off = common.flat_text(column)
    _, _, h, first = common.words_of(raw, off)
    n_words = np.diff(first)
    base = (n_words < 20) | (100 * repeated_in_windows(_rank(h), first) > 30 * n_words)
    pack = zstandard.ZstdCompressor(level=bands.level)
    good = ~base
    blob, size = raw.tobytes(), np.diff(off)
    lo, hi = _limits(bands.whole, size)
    for i in np.flatnonzero(good).tolist():
        r, parts = ratios(blob[off[i] : off[i + 1]], pack, bands.chunk_bytes)
        n, part = np.array(parts).T
        a, b = _limits(bands.chunk, n)
        good[i] = lo[i] <= r <= hi[i] and max((part < a).sum(), (part > b).sum()) <= bands.bad_chunks * len(part)
    return pc.fill_null(pa.array(good), False)
