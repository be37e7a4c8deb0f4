"""Hierarchical multi-length packing.

Documents longer than the widest context are cut into full windows; what is left is an item.
Items are routed to the smallest tier (context size) that holds them.  Windows are opened by
the longest items first, so wide windows are closed before narrow tiers are packed, and each
window's gap is filled from shorter tiers: the longest item that fits, again and again, then a
cut of the shortest item that is longer than the gap.  So every window is full but the last of a
group, which alone is padded.  Windows are dealt to step groups so that attention cost is even.

A group is a run of whole documents of about ``GROUP_TOKENS`` ids within one input partition:
there is no shuffle, and a worker's memory is bounded by a group.

Defined cases: a null text is an empty document (only the end id); an empty table gives no rows;
repeated documents are packed each; other columns of the input are ignored.
"""

from __future__ import annotations

import heapq
import zlib
from bisect import bisect_left, bisect_right, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

TIERS = (128, 256, 512, 1024)
GROUP_TOKENS = 2_000_000
STEP_TOKENS = 65_536


def plan_group(lengths: list[int], tiers: tuple[int, ...] = TIERS) -> list[tuple[int, list[tuple[int, int, int]]]]:
    """Pack documents of the given lengths: [(window size, [(document, start, length), ...])].
    All windows are full, but for at most the last."""
    wide = tiers[-1]
    out: list[tuple[int, list[tuple[int, int, int]]]] = []
    pool: list[tuple[int, int, int]] = []  # (length, document, start)
    for d, n in enumerate(lengths):
        full = n - n % wide
        out.extend((wide, [(d, s, wide)]) for s in range(0, full, wide))
        if n > full:
            pool.append((n - full, d, full))
    pool.sort()
    while pool:
        n, d, s = pool.pop()
        size = tiers[bisect_left(tiers, n)]
        pieces, gap = [(d, s, n)], size - n
        while gap and pool:
            k = bisect_right(pool, (gap, 1 << 62, 0))
            if k:
                n, d, s = pool.pop(k - 1)
                pieces.append((d, s, n))
                gap -= n
            else:
                n, d, s = pool.pop(0)
                pieces.append((d, s, gap))
                insort(pool, (n - gap, d, s + gap))
                gap = 0
        out.append((size, pieces))
    return out


def balance(costs: list[int], n_groups: int) -> list[int]:
    """Deal windows to step groups of nearly equal cost, the most costly first."""
    heap = [(0, g) for g in range(max(1, n_groups))]
    out = [0] * len(costs)
    for i in sorted(range(len(costs)), key=lambda i: (-costs[i], i)):
        total, g = heap[0]
        heapq.heapreplace(heap, (total + costs[i], g))
        out[i] = g
    return out


PACK_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier long, sequence_length long, step_group long"


def pack(docs: DataFrame, tokenizer: str, end_id: int = 0, tiers: tuple[int, ...] = TIERS, group_tokens: int = GROUP_TOKENS, with_ids: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece; ``with_ids`` adds the ids themselves (array<int>)."""
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    names = [c.split()[0] for c in PACK_SCHEMA.split(", ")] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, group = TaskContext.get().partitionId(), 0
        enc = common.encoder(tokenizer)
        held: list[tuple[object, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal held, size, group
            held.sort(key=lambda x: (x[0] is not None, x[0] or 0, len(x[1]), x[1].tobytes()))
            windows = plan_group([len(x[1]) for x in held], tiers)
            lengths = [sum(p[2] for p in w[1]) for w in windows]
            steps = balance([sum(p[2] ** 2 for p in w[1]) + w[0] for w in windows], -(-sum(lengths) // STEP_TOKENS))
            cols: list[list] = [[] for _ in names]
            for k, (tier, pieces) in enumerate(windows):
                at = 0
                for d, s, n in pieces:
                    name, ids = held[d]
                    row = [name, s, n, zlib.crc32(ids[s : s + n]), len(ids), part << 36 | group << 24 | k, at, tier, lengths[k], part << 36 | group << 24 | steps[k]]
                    if with_ids:
                        row.append(ids[s : s + n].astype(np.int32))
                    for c, v in zip(cols, row, strict=True):
                        c.append(v)
                    at += n
            held, size, group = [], 0, group + 1
            kinds = [pa.int64()] * 10 + [pa.list_(pa.int32())] * with_ids
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

        for batch in common.slices(batches, "text", encoding=True):
            ids, offsets = enc.encode(batch.column("text"))
            ids = np.insert(ids, offsets[1:], end_id).astype("<u4")
            edges = offsets + np.arange(len(offsets))
            for k, name in enumerate(batch.column("doc_id").to_pylist()):
                held.append((name, ids[edges[k] : edges[k + 1]]))
                size += int(edges[k + 1] - edges[k])
                if size >= group_tokens:
                    yield flush()
        if held:
            yield flush()

    return src.mapInArrow(run, PACK_SCHEMA + ", ids array<int>" * with_ids)


def padding_report(pieces: DataFrame, wide: int = TIERS[-1]) -> DataFrame:
    """Windows, ids and padding by tier: a window is padded to ``wide`` unless its length is a power of two."""
    w = pieces.groupBy("sequence_id").agg(F.max("tier").alias("tier"), F.sum("length").alias("n"))
    pad = F.when(F.col("n").bitwiseAND(F.col("n") - 1) == 0, 0).otherwise(wide - F.col("n"))
    return w.groupBy("tier").agg(F.count("*").alias("sequences"), F.sum("n").alias("ids"), F.sum(pad).alias("padding"))
