"""Benchmark decontamination by SimHash of item-sized windows.

Texts are lower-cased (ASCII) and split at white space and ASCII punctuation.  A benchmark item of n
words is compared with windows of n words of each document (or the whole document, if shorter).
Windows and items are weighted sets of 5-word shingles, a shingle weighing the bytes of its words;
their 64-bit SimHash fingerprints are matched by a multi-index: the fingerprint is cut into
``RADIUS + 1`` blocks, and two fingerprints within the radius agree in one block at least, so every item within the
radius is found.  Candidates are then verified by the exact weighted similarity (common weight / united
weight, with multiplicity), which must reach 0.8.

Only windows that hold a shingle of an item of that size are fingerprinted: any other window has
similarity 0 with all items of that size.  At a true similarity of 0.8 the fingerprints of the best window differ by some 10
bits; the radius is three deviations above.

The benchmark is read in parts of at most ``PART_BYTES``; each part is an index of that bound in
every worker, and a larger benchmark takes more passes over the documents.

Defined cases: null texts and items are empty and match nothing; items of fewer than five words are one shingle;
repeated items each match; repeated documents get equal rows; an empty table gives no rows, an empty benchmark keeps
all; other columns are ignored by ``find`` and kept by ``clean``.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

WORDS, SIMILARITY, BITS, RADIUS = 5, 0.8, 64, 19
PART_BYTES = 8 << 20
HITS = "array<struct<item_id:bigint,similarity:double,first_word:int,n_words:int>>"
_SEEDS = common.mix(np.arange(1, 5, dtype=np.uint64))


def weighted_shingles(column: pa.Array):
    """Per text: word count; and over all: shingle hashes, weights, first shingles."""
    raw, off = common.flat_text(column)
    start, end, h, first = common.words_of(raw, off, lower=True, breaks=common.PUNCTUATION)
    g, at = common.shingles(h, first, WORDS)
    size = np.concatenate([[0], np.cumsum(end - start)])
    n = np.diff(first)
    count = np.diff(at)
    a = common.gather(first[:-1], count)
    b = a + np.repeat(np.minimum(n, WORDS), count)
    return n, g, (size[b] - size[a]).astype(np.int64), at


def _signs(g: np.ndarray) -> np.ndarray:
    """(shingles, 64) of +1 and -1."""
    return np.unpackbits(common.mix(g).view(np.uint8).reshape(-1, 8), axis=1).astype(np.int8) * 2 - 1


def fingerprints(total: np.ndarray) -> np.ndarray:
    return np.packbits(total > 0, axis=1).view(np.uint64).reshape(-1)


class Index:
    """Items of one part of the benchmark, by size, shingle and fingerprint block."""

    def __init__(self, item_ids: list[int], texts: list[str]):
        n, g, w, at = weighted_shingles(pa.array(texts, pa.string()))
        self.sizes: dict[int, list[int]] = {}
        self.items = []
        for i, item in enumerate(item_ids):
            if n[i]:
                s, v = g[at[i] : at[i + 1]], w[at[i] : at[i + 1]]
                self.sizes.setdefault(int(n[i]), []).append(len(self.items))
                self.items.append((item, int(n[i]), Counter(dict(_sum(s, v))), Counter(dict(_sum(s, np.ones(len(s), np.int64)))), dict(zip(s.tolist(), v.tolist(), strict=True)), int(fingerprints((_signs(s) * v[:, None]).sum(0, dtype=np.int64)[None])[0])))
        self.shingles = np.unique(np.concatenate([np.fromiter(x[2], np.uint64) for x in self.items])) if self.items else np.zeros(0, np.uint64)
        owners = sorted({(s, x[1]) for x in self.items for s in x[2]})
        self.of_shingle: dict[int, list[int]] = {}
        for s, size in owners:
            self.of_shingle.setdefault(s, []).append(size)
        self.mask = np.zeros(1 << 22, bool)
        self.mask[(self.shingles & np.uint64((1 << 22) - 1)).astype(np.int64)] = True
        edges = np.linspace(0, BITS, RADIUS + 2).astype(int)
        self.blocks = [(int(a), (1 << int(b - a)) - 1) for a, b in zip(edges, edges[1:], strict=False)]
        self.table: dict[int, list[dict[int, list[int]]]] = {}
        for size, members in self.sizes.items():
            t = self.table[size] = [{} for _ in self.blocks]
            for k in members:
                for d, (a, m) in zip(t, self.blocks, strict=True):
                    d.setdefault(self.items[k][5] >> a & m, []).append(k)

    def hits(self, g: np.ndarray) -> np.ndarray:
        """Positions of shingles that some item has."""
        may = np.flatnonzero(self.mask[(g & np.uint64((1 << 22) - 1)).astype(np.int64)])
        at = np.searchsorted(self.shingles, g[may])
        return may[self.shingles[np.minimum(at, len(self.shingles) - 1)] == g[may]] if len(self.shingles) else may[:0]

    def near(self, size: int, print_: int) -> set[int]:
        """Items of a size whose fingerprints lie within the radius: all of them share a block."""
        seen: set[int] = set()
        for d, (a, m) in zip(self.table[size], self.blocks, strict=True):
            seen.update(d.get(print_ >> a & m, ()))
        return {k for k in seen if (self.items[k][5] ^ print_).bit_count() <= RADIUS}

    def match(self, n: int, g: np.ndarray, w: np.ndarray, at: np.ndarray) -> list[tuple[int, float, int, int]]:
        """Verified items of one document: (item, best similarity, first word, words)."""
        best: dict[int, tuple[float, int, int]] = {}
        starts: dict[int, set[int]] = {}
        for p in at.tolist():
            for size in self.of_shingle[int(g[p])]:
                width = min(size, n)
                span = max(width - WORDS + 1, 1)  # shingles in a window
                lo, hi = max(0, p - span + 1), min(p, len(g) - span)
                starts.setdefault(size, set()).update(range(lo, hi + 1))
        for size, found in sorted(starts.items()):
            width = min(size, n)
            span = max(width - WORDS + 1, 1)
            todo = np.array(sorted(found))
            for part in np.split(todo, np.flatnonzero(np.diff(todo) > 1) + 1):
                a, b = int(part[0]), int(part[-1]) + span
                run = np.concatenate([np.zeros((1, BITS), np.int64), np.cumsum(_signs(g[a:b]).astype(np.int64) * w[a:b, None], axis=0)])
                prints = fingerprints(run[part - a + span] - run[part - a])
                for s, fp in zip(part.tolist(), prints.tolist(), strict=True):
                    for k in self.near(size, fp):
                        sim = self.similarity(k, g[s : s + span], w[s : s + span])
                        if sim >= SIMILARITY and sim > best.get(k, (0.0,))[0]:
                            best[k] = (sim, s, width)
        return [(self.items[k][0], *v) for k, v in sorted(best.items())]

    def similarity(self, k: int, g: np.ndarray, w: np.ndarray) -> float:
        _, _, weight, count, each, _ = self.items[k]
        common_w = 0
        for s, c in Counter(g.tolist()).items():
            if s in each:
                common_w += min(c, count[s]) * each[s]
        return common_w / (sum(weight.values()) + int(w.sum()) - common_w)


def _sum(keys: np.ndarray, values: np.ndarray):
    out: Counter = Counter()
    for k, v in zip(keys.tolist(), values.tolist(), strict=True):
        out[k] += v
    return out


def parts_of(benchmark: DataFrame, item_id: str = "item_id", text: str = "text") -> Iterator[list[tuple[int, str]]]:
    """The benchmark in parts of bounded size, by a hash of the item."""
    items = benchmark.select(F.col(item_id).cast("long").alias("item_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    total = items.agg(F.sum(F.octet_length("text") + 64)).first()[0] or 0
    n = max(1, -(-2 * total // PART_BYTES)) if total > PART_BYTES else 1
    for k in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)
        yield [(r[0], r[1]) for r in part.collect()]


def find(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: doc_id, hits (verified items), and kept (no hits).  No shuffle for a
    benchmark of one part; a further part adds one pass whose output is the input's rows."""
    out = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"), F.array().cast(HITS).alias("hits"))
    for part in parts_of(benchmark):
        out = _pass(out, part)
    return out.select("doc_id", "hits", (F.size("hits") == 0).alias("kept"))


def _pass(docs: DataFrame, part: list[tuple[int, str]], text: str = "text") -> DataFrame:
    items = docs.sparkSession.sparkContext.broadcast(part)
    schema, where = docs.schema, docs.columns.index(text)
    held: list[Index] = []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not held:
            held.append(Index([x[0] for x in items.value], [x[1] for x in items.value]))
        for batch in common.slices(batches, text):
            found = hits_of(batch.column(where), held[0])
            k = batch.schema.get_field_index("hits")
            old = batch.column(k).to_pylist()
            new = [a + [dict(zip(("item_id", "similarity", "first_word", "n_words"), x, strict=True)) for x in found.get(i, ())] for i, a in enumerate(old)]
            yield batch.set_column(k, batch.schema.field(k), pa.array(new, batch.schema.field(k).type))

    return docs.mapInArrow(run, schema)


def hits_of(column: pa.Array, index: Index) -> dict[int, list[tuple[int, float, int, int]]]:
    """Matches of each text of a column that has any."""
    n, g, w, at = weighted_shingles(column)
    hit = index.hits(g)
    owner = np.searchsorted(at, hit, side="right") - 1
    out = {}
    for i in np.unique(owner).tolist():
        a, b = int(at[i]), int(at[i + 1])
        if got := index.match(int(n[i]), g[a:b], w[a:b], hit[owner == i] - a):
            out[i] = got
    return out


def clean(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents without a verified item, with all their columns."""
    out, schema, where = docs, docs.schema, docs.columns.index(text)
    for part in parts_of(benchmark):
        items = docs.sparkSession.sparkContext.broadcast(part)

        def run(batches: Iterator[pa.RecordBatch], items=items) -> Iterator[pa.RecordBatch]:
            index = Index([x[0] for x in items.value], [x[1] for x in items.value])
            for batch in common.slices(batches, text):
                gone = np.zeros(batch.num_rows, bool)
                gone[list(hits_of(batch.column(where), index))] = True
                yield batch.filter(pa.array(~gone))

        out = out.mapInArrow(run, schema)
    return out
