"""Token-id output as wavelet matrices, one self-contained compressed image per shard.

An image holds the ids of whole documents as bit-planes, most significant first.  In each
plane the entries stand in the stable order given by the planes above (zeros first).  A plane
is cut into blocks of 65,536 bits, each zstandard-compressed on its own, with the number of
ones before every block.  So one token is read, counted or located by opening one block of each
plane, and a whole shard is decoded by undoing the partitions from the last plane up.

Defined cases: a null text is an empty document (only the end id); an empty table gives no
shard and no rows; repeated doc_id values stand side by side, ordered by text; null doc_id
sorts first; other columns of the input are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

MAGIC = b"WVMX0001"
BLOCK = 1 << 13  # bytes of a plane's block
SHARD_TOKENS = 1 << 20


def build_image(ids: np.ndarray, doc_ids: np.ndarray, offsets: np.ndarray, bits: int = 16) -> bytes:
    """The image of a shard: ``ids`` of documents ``doc_ids`` that begin at ``offsets[:-1]``."""
    n = len(ids)
    if n and int(ids.max()) >> bits:
        raise ValueError(f"an id needs more than {bits} bits")
    seq = ids.astype(np.uint16 if bits <= 16 else np.uint32)
    pack = zstandard.ZstdCompressor(level=1)
    body, directory = [], []
    at = 0
    for k in range(bits - 1, -1, -1):
        ones = (seq & seq.dtype.type(1 << k)) != 0
        raw = np.packbits(ones)
        n_blocks = -(-len(raw) // BLOCK)
        count = np.add.reduceat(np.bitwise_count(raw), np.arange(0, len(raw), BLOCK), dtype=np.int64) if n else np.zeros(0, np.int64)
        before = np.concatenate([[0], np.cumsum(count)])
        for b in range(n_blocks):
            part = raw[b * BLOCK : (b + 1) * BLOCK].tobytes()
            small = pack.compress(part)
            kept, packed = (small, 1) if len(small) < len(part) else (part, 0)
            directory.append((at, len(kept), packed, int(before[b])))
            body.append(kept)
            at += len(kept)
        directory.append((at, 0, 0, int(before[-1])))  # the plane's ones
        seq = np.concatenate([seq[~ones], seq[ones]])
    head = pack.compress(np.array(directory, "<i8").tobytes())
    docs = pack.compress(np.concatenate([doc_ids.astype("<i8"), offsets.astype("<i8")]).tobytes())
    return b"".join([MAGIC, struct.pack("<qqqqq", n, bits, len(doc_ids), len(head), len(docs)), head, docs, *body])


class WaveletShard:
    """Reads an image; single look-ups open only the blocks they touch."""

    def __init__(self, image: bytes):
        if image[:8] != MAGIC:
            raise ValueError("not a wavelet image")
        self.n, self.bits, n_docs, n_head, n_docs_raw = struct.unpack("<qqqqq", image[8:48])
        unpack = self._unpack = zstandard.ZstdDecompressor()
        self.n_blocks = -(-(-(-self.n // 8)) // BLOCK)
        head = np.frombuffer(unpack.decompress(image[48 : 48 + n_head]), "<i8").reshape(self.bits, self.n_blocks + 1, 4)
        self.head = head
        docs = np.frombuffer(unpack.decompress(image[48 + n_head : 48 + n_head + n_docs_raw]), "<i8")
        self.doc_ids, self.offsets = docs[:n_docs], docs[n_docs:]
        self.body = memoryview(image)[48 + n_head + n_docs_raw :]
        self.zeros = [self.n - int(head[p, -1, 3]) for p in range(self.bits)]

    def _block(self, plane: int, b: int) -> np.ndarray:
        at, size, packed, _ = (int(x) for x in self.head[plane, b])
        part = bytes(self.body[at : at + size])
        if packed:
            part = self._unpack.decompress(part, max_output_size=BLOCK)
        return np.frombuffer(part, np.uint8)

    def _plane(self, plane: int) -> np.ndarray:
        raw = np.concatenate([self._block(plane, b) for b in range(self.n_blocks)]) if self.n_blocks else np.zeros(0, np.uint8)
        return np.unpackbits(raw)[: self.n].view(bool)

    def _rank1(self, plane: int, i: int) -> int:
        """Ones of a plane before position i."""
        b, rest = divmod(i, BLOCK * 8)
        if rest == 0:
            return int(self.head[plane, b, 3])
        bits = np.unpackbits(self._block(plane, b)[: -(-rest // 8)])[:rest]
        return int(self.head[plane, b, 3]) + int(bits.sum())

    def _bit(self, plane: int, i: int) -> int:
        b, rest = divmod(i, BLOCK * 8)
        return int(self._block(plane, b)[rest >> 3] >> (7 - (rest & 7)) & 1)

    def _select(self, plane: int, one: int, k: int) -> int:
        """Position of the k-th (from 0) one or zero of a plane."""
        before = self.head[plane, :, 3]
        if not one:
            before = np.minimum(np.arange(self.n_blocks + 1) * BLOCK * 8, self.n) - before
        b = int(np.searchsorted(before, k, side="right")) - 1
        bits = np.unpackbits(self._block(plane, b))
        return b * BLOCK * 8 + int(np.flatnonzero(bits == one)[k - int(before[b])])

    def access(self, i: int) -> int:
        if not 0 <= i < self.n:
            raise IndexError(i)
        out = 0
        for p in range(self.bits):
            one = self._bit(p, i)
            r = self._rank1(p, i)
            i = self.zeros[p] + r if one else i - r
            out = out << 1 | one
        return out

    def _range(self, token: int, lo: int, hi: int) -> tuple[int, int]:
        for p in range(self.bits):
            a, b = self._rank1(p, lo), self._rank1(p, hi)
            if token >> (self.bits - 1 - p) & 1:
                lo, hi = self.zeros[p] + a, self.zeros[p] + b
            else:
                lo, hi = lo - a, hi - b
        return lo, hi

    def rank(self, token: int, i: int) -> int:
        """Occurrences of a token before position i."""
        if token >> self.bits:
            return 0
        lo, hi = self._range(token, 0, i)
        return hi - lo

    def count(self, token: int) -> int:
        return self.rank(token, self.n)

    def select(self, token: int, k: int) -> int:
        """Position of the k-th (from 0) occurrence of a token."""
        lo, hi = self._range(token, 0, self.n) if not token >> self.bits else (0, 0)
        if not 0 <= k < hi - lo:
            raise IndexError(k)
        i = lo + k
        for p in range(self.bits - 1, -1, -1):
            one = token >> (self.bits - 1 - p) & 1
            i = self._select(p, one, i - self.zeros[p] if one else i)
        return i

    def occurrences(self, token: int) -> list[int]:
        return [self.select(token, k) for k in range(self.count(token))]

    def decode(self) -> np.ndarray:
        """All ids of the shard, in order."""
        kind = np.uint16 if self.bits <= 16 else np.uint32
        seq = np.zeros(self.n, kind)
        for p in range(self.bits - 1, -1, -1):
            ones, z = self._plane(p), self.zeros[p]
            up = np.empty_like(seq)
            up[~ones] = seq[:z]
            up[ones] = seq[z:] | kind(1 << (self.bits - 1 - p))
            seq = up
        return seq

    def document(self, k: int) -> np.ndarray:
        """Ids of the k-th document, by single look-ups."""
        return np.array([self.access(i) for i in range(int(self.offsets[k]), int(self.offsets[k + 1]))], np.uint32)


SHARD_SCHEMA = "part int, shard int, n_docs long, n_tokens long, image binary"


def write_shards(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, shard_tokens: int = SHARD_TOKENS, bits: int = 16, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Encode documents in ascending doc_id order and write shards to ``path``.

    Spark's own writer commits the images, so a lost executor leaves no half shard.  One
    range shuffle by doc_id; a task holds one shard and one slice of text at a time."""
    spark = docs.sparkSession
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, shard = TaskContext.get().partitionId(), 0
        enc = common.encoder(tokenizer)
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal held, size, shard
            ids = np.concatenate([h[0] for h in held])
            names = np.concatenate([h[1] for h in held])
            offsets = np.concatenate([[0], np.cumsum(np.concatenate([h[2] for h in held]))])
            image = build_image(ids, names, offsets, bits)
            row = [[part], [shard], [len(names)], [len(ids)], [image]]
            kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
            held, size, shard = [], 0, shard + 1
            return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(row, kinds, strict=True)], ["part", "shard", "n_docs", "n_tokens", "image"])

        for batch in common.slices(batches, "text", encoding=True):
            ids, offsets = enc.encode(batch.column("text"))
            # a null doc_id is kept as the smallest long, which sorts first as well
            names = batch.column("doc_id").fill_null(-(1 << 63)).to_numpy(zero_copy_only=False)
            ids = np.insert(ids, offsets[1:], end_id)
            lengths = np.diff(offsets) + 1
            edges = np.concatenate([[0], np.cumsum(lengths)])
            a = 0
            while a < len(names):
                room = max(shard_tokens - size, 0)
                b = max(int(np.searchsorted(edges, edges[a] + room, side="right")) - 1, a + (size == 0))
                if b > a:
                    held.append((ids[edges[a] : edges[b]], names[a:b], lengths[a:b]))
                    size += int(edges[b] - edges[a])
                a = b
                if a < len(names) or size >= shard_tokens:
                    yield flush()
        if held:
            yield flush()

    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    src.repartitionByRange(n, "doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(encode, SHARD_SCHEMA).write.option("compression", "uncompressed").parquet(path)
    return spark.read.schema(SHARD_SCHEMA).parquet(path)


def read_documents(shards: DataFrame) -> DataFrame:
    """Decode shards: per document doc_id, start, n_tokens, ids_crc32.

    Start positions come from the token counts of the range parts (as many rows as shuffle
    partitions, so they are broadcast) and of the shards before within a part."""
    manifest = shards.select("part", "shard", "n_tokens")
    per_part = manifest.groupBy("part").agg(F.sum("n_tokens").alias("part_tokens"))
    base = per_part.select("part", (F.sum("part_tokens").over(Window.orderBy("part")) - F.col("part_tokens")).alias("part_start"))
    within = manifest.select("part", "shard", (F.sum("n_tokens").over(Window.partitionBy("part").orderBy("shard")) - F.col("n_tokens")).alias("shard_start"))
    placed = within.join(F.broadcast(base), "part").select("part", "shard", (F.col("part_start") + F.col("shard_start")).alias("shard_start"))

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                shard = WaveletShard(batch.column(2)[k].as_py())
                ids = shard.decode().astype("<u4")
                off, part = shard.offsets, batch.column(0)[k].as_py()
                names = pa.array(shard.doc_ids, pa.int64(), mask=shard.doc_ids == -(1 << 63))
                crc = [zlib.crc32(ids[a:b]) for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
                m = len(crc)
                yield pa.RecordBatch.from_arrays([pa.array([part] * m, pa.int32()), pa.array([batch.column(1)[k].as_py()] * m, pa.int32()), names, pa.array(off[:-1].astype(np.int64)), pa.array(np.diff(off).astype(np.int64)), pa.array(crc, pa.int64())], ["part", "shard", "doc_id", "local", "n_tokens", "ids_crc32"])

    rows = shards.select("part", "shard", "image").mapInArrow(decode, "part int, shard int, doc_id long, local long, n_tokens long, ids_crc32 long")
    return rows.join(F.broadcast(placed), ["part", "shard"]).select("doc_id", (F.col("shard_start") + F.col("local")).alias("start"), "n_tokens", "ids_crc32", "part", "shard")


def token_counts(shards: DataFrame, tokens: list[int]) -> DataFrame:
    """Occurrences of some tokens per shard, by rank look-ups in the images."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                shard = WaveletShard(batch.column(2)[k].as_py())
                yield pa.RecordBatch.from_arrays([pa.array([batch.column(0)[k].as_py()] * len(tokens), pa.int32()), pa.array([batch.column(1)[k].as_py()] * len(tokens), pa.int32()), pa.array(tokens, pa.int64()), pa.array([shard.count(t) for t in tokens], pa.int64())], ["part", "shard", "token", "n"])

    return shards.select("part", "shard", "image").mapInArrow(count, "part int, shard int, token long, n long")
