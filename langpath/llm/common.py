"""Shared pieces of the training-data operators: shared storage, Arrow text access,
vectorised word hashing and exact, cached tokenisation."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Texts are handled in slices of about so many bytes, which bounds a worker's memory.
SLICE_BYTES = 2 << 20
SHUFFLE_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


# --------------------------------------------------------------------------- storage
def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share.  A cluster names it in
    ``spark.checkpoint.dir``; only where that is unset (tests) an own one is made."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = getattr(shared_root, "own", None) or f"file://{tempfile.mkdtemp(prefix='langpath-')}"
        shared_root.own = root
    return root.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/langpath-{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there, so a lost
    executor never replays what stands before."""
    spark = df.sparkSession
    path = new_path(spark, name)
    before = spark.conf.get(SHUFFLE_CLEANUP, None)
    spark.conf.set(SHUFFLE_CLEANUP, "true")  # the table is what is read from now on, so its shuffles go at once
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(SHUFFLE_CLEANUP) if before is None else spark.conf.set(SHUFFLE_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out.shared_path = path
    return out


def drop_cut(*frames: DataFrame) -> None:
    """Delete tables made by :func:`cut` that nothing reads any more."""
    for df in frames:
        path = getattr(df, "shared_path", None)
        if path:
            jvm = df.sparkSession._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(p, True)


def read(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


# --------------------------------------------------------------------------- Arrow text
def flat_text(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null reads as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    column = column.cast(pa.large_string())
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def trim() -> None:
    """Give freed memory back: Arrow's pool, and the C heap where it can be trimmed."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def forget_encoders() -> None:
    """Workers are reused: one that does not encode has no need of what encoders have cached."""
    if _encoders:
        _encoders.clear()
        trim()


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = SLICE_BYTES, encoding: bool = False) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each holds about ``limit`` bytes of ``text``; a longer
    single text stays whole.  Workers are reused by other operators, so one that does not
    encode first drops what encoders have cached."""
    if not encoding:
        forget_encoders()
    for batch in batches:
        if batch.num_rows == 0:
            continue
        col = batch.column(batch.schema.get_field_index(text))
        sizes = pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        part = (np.cumsum(sizes) - sizes) // limit
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            yield batch.slice(a, b - a)
        del batch, col
        if not encoding:
            trim()


# --------------------------------------------------------------------------- words
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
#: White space, control characters and ASCII punctuation.
PUNCTUATION = np.array([b < 0x80 and not chr(b).isalnum() for b in range(256)])
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[str, np.ndarray] = {}


def _power_table(kind: str, n: int) -> np.ndarray:
    have = _powers.get(kind)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        table = np.full(size, np.uint64(_BASE if kind == "up" else _INVERSE))
        table[0] = 1
        have = _powers[kind] = np.multiply.accumulate(table)
    return have


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def prefix_hash(raw: np.ndarray) -> np.ndarray:
    """Prefix sums that give the hash of any byte range by :func:`range_hash`."""
    out = np.zeros(len(raw) + 1, np.uint64)
    term = out[1:]
    term[:] = raw
    term += np.uint64(1)
    term *= _power_table("up", len(raw) + 1)[: len(raw)]
    np.cumsum(term, out=term)
    return out


def range_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hash of the bytes [start, end), the same wherever the bytes stand."""
    down = _power_table("down", len(prefix))
    return mix((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def words_of(raw: np.ndarray, offsets: np.ndarray, lower: bool = False, breaks: np.ndarray = _SPACE):
    """Words (runs of bytes outside ``breaks``: 0x20 and 0x09-0x0D) of concatenated texts.

    Returns (start, end, hash, first): byte ranges and hashes of all words, and for each
    text the index of its first word (one entry more than texts)."""
    n = len(raw)
    if lower:
        raw = _LOWER[raw]
    solid = ~breaks[raw]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    left = np.empty(n, bool)
    right = np.empty(n, bool)
    if n:
        left[0], right[-1] = True, True
        left[1:] = ~solid[:-1] | edge[1:n]
        right[:-1] = ~solid[1:] | edge[1:n]
    start = np.flatnonzero(solid & left)
    end = np.flatnonzero(solid & right) + 1
    h = range_hash(prefix_hash(raw), start, end)
    return start, end, h, np.searchsorted(start, offsets)


def gather(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices of the ranges [starts, starts+lengths), one after another."""
    total = int(lengths.sum())
    if total == 0:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lengths)
    return np.arange(total, dtype=np.int64) + np.repeat(starts - (ends - lengths), lengths)


# --------------------------------------------------------------------------- tokens
def tokenizer_file(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ExactEncoder:
    """Byte-level BPE of whole texts, each distinct word form of a slice encoded once.

    A pre-token of this vocabulary always begins at a single space or line feed between two
    other characters, so a text may be cut before it and its pieces encoded alone.  Texts with
    white space beside white space are encoded whole.  Pieces are encoded many at a time, each
    led by a line feed, which is a token of its own there.

    Forms already encoded are kept in flat arrays, sorted by hash: at most ``_cached`` of them, some 40
    bytes each.  A form is known only if its bytes are equal, not just its hash."""

    _joined = 1024
    _cached = 1_000_000

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self._fast = getattr(self.tok, "encode_batch_fast", self.tok.encode_batch)
        # by form, in order of hash: hash, first byte, bytes, first id, ids
        self._hash = np.zeros(0, np.uint64)
        self._from, self._size = np.zeros(0, np.int32), np.zeros(0, np.int32)
        self._at, self._len = np.zeros(0, np.int32), np.zeros(0, np.int32)
        self._bytes, self._ids = np.zeros(0, np.uint8), np.zeros(0, np.uint32)
        probe = self.tok.encode("\n", add_special_tokens=False).ids
        self.line_feed = probe[0] if len(probe) == 1 else None
        self._check()

    def _check(self) -> None:
        """Cutting is used only where it holds for the vocabulary at hand."""
        text = "Ab, c'd  é\nF-1 \tg %% 22 h.\n\nI x"
        got = self.line_feed is not None and self._cut_ok([" Ab,", " c'd", " é", " 22%%"]) and self._cut_ok(["I'm"]) and self._cut_ok(["22"])
        self.can_cut = bool(got) and self.tok.encode(text, add_special_tokens=False).ids == self.encode_one(text)

    def _cut_ok(self, pieces: list[str]) -> bool:
        whole = self.tok.encode("".join(pieces), add_special_tokens=False).ids
        joined = self.tok.encode("".join("\n" + p for p in pieces), add_special_tokens=False).ids
        flat = [i for p in pieces for i in self.tok.encode(p, add_special_tokens=False).ids]
        return whole == flat and [i for i in joined if i != self.line_feed] == flat

    def encode_one(self, text: str) -> list[int]:
        return self.tok.encode(text, add_special_tokens=False).ids

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids uint32, offsets) of the texts of a column; null reads as empty."""
        texts = pc.fill_null(column, "").cast(pa.large_string())
        n = len(texts)
        raw, off = flat_text(texts)
        if n == 0 or len(raw) == 0:
            return np.zeros(0, np.uint32), np.zeros(n + 1, np.int64)
        if self.can_cut:
            whole = pc.match_substring_regex(texts, r"[\p{Z}\s\x00-\x1f\x85][ \n]|^[ \n]|[ \n]$").to_numpy(zero_copy_only=False)
        else:
            whole = np.ones(n, bool)
        edge = (raw == 0x20) | (raw == 0x0A)
        edge &= ~np.repeat(whole, np.diff(off))
        edge[off[:-1][np.diff(off) > 0]] = True
        start = np.flatnonzero(edge)
        end = np.append(start[1:], len(raw))
        first = np.searchsorted(start, off)
        coded = pa.array(range_hash(prefix_hash(raw), start, end)).dictionary_encode()
        code = coded.indices.to_numpy(zero_copy_only=False)
        where = np.empty(len(coded.dictionary), np.int64)
        where[code[::-1]] = np.arange(len(code) - 1, -1, -1)
        size = end - start
        if (size != size[where[code]]).any() or (raw[gather(start[where[code]], size)] != raw).any():
            lists = [e.ids for e in self._fast(texts.to_pylist(), add_special_tokens=False)]  # two forms share a hash
            lens = np.array([len(x) for x in lists], np.int64)
            return np.array([i for x in lists for i in x], np.uint32), np.concatenate([[0], np.cumsum(lens)])
        alone = np.repeat(whole, np.diff(first))[where]
        ids, at, lens = self._forms(raw, coded.dictionary.to_numpy(zero_copy_only=False), start[where], size[where], alone)
        per_piece = lens[code]
        total = np.concatenate([[0], np.cumsum(per_piece)])
        return ids[gather(at[code], per_piece)], total[first]

    def _forms(self, raw: np.ndarray, h: np.ndarray, start: np.ndarray, size: np.ndarray, alone: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, at, lengths) of distinct forms; ``alone`` are whole texts, which are not kept."""
        at, lens = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        pos = np.searchsorted(self._hash, h)
        known = np.zeros(len(h), bool)
        inside = np.flatnonzero(pos < len(self._hash))
        inside = inside[(self._hash[pos[inside]] == h[inside]) & (self._size[pos[inside]] == size[inside])]
        if len(inside):
            n = size[inside]
            same = raw[gather(start[inside], n)] == self._bytes[gather(self._from[pos[inside]].astype(np.int64), n)]
            inside = inside[np.logical_and.reduceat(same, np.cumsum(n) - n)]
            known[inside] = True
        old = pos[inside]
        lens[inside] = self._len[old]
        at[inside] = np.cumsum(lens[inside]) - lens[inside]
        have = self._ids[gather(self._at[old].astype(np.int64), lens[inside])]
        new = np.flatnonzero(~known)
        if not len(new):
            return have, at, lens
        ids, lens[new] = self._encode_new(raw, start[new], size[new], alone[new])
        at[new] = len(have) + np.cumsum(lens[new]) - lens[new]
        self._keep(raw, h, start, size, new, alone, ids, at - len(have), lens)
        return np.concatenate([have, ids]), at, lens

    def _encode_new(self, raw: np.ndarray, start: np.ndarray, size: np.ndarray, alone: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        forms = _strings(raw[gather(start, size)], size)
        easy = pc.match_substring_regex(forms, r"^[ \n]?[^\p{Z}\s\x00-\x1f\x85]+$").to_numpy(zero_copy_only=False)
        easy &= ~pc.match_substring(forms, "<|").to_numpy(zero_copy_only=False) & ~alone
        lens = np.zeros(len(start), np.int64)
        chunks, done = [], []
        simple = np.flatnonzero(easy)
        own = raw[start] == 0x0A  # brings its line feed, which stays
        for a in range(0, len(simple), self._joined * 16):
            some = simple[a : a + self._joined * 16]
            lead = np.where(own[some], 0, 1)
            size_ = size[some] + lead
            out = np.full(int(size_.sum()), 0x0A, np.uint8)
            begin = np.cumsum(size_) - size_
            out[gather(begin + lead, size[some])] = raw[gather(start[some], size[some])]
            cuts = [*begin[:: self._joined].tolist(), len(out)]
            for k, enc in enumerate(self._fast([out[x:y].tobytes().decode() for x, y in zip(cuts, cuts[1:], strict=False)], add_special_tokens=False)):
                part = some[k * self._joined : (k + 1) * self._joined]
                got = np.array(enc.ids, np.uint32)
                feeds = np.flatnonzero(got == self.line_feed)
                if len(feeds) != len(part):
                    easy[part] = False  # encoded one by one below
                    continue
                drop = ~own[part]
                lens[part] = np.diff(np.append(feeds, len(got))) - drop
                stay = np.ones(len(got), bool)
                stay[feeds[drop]] = False
                chunks.append(got[stay])
                done.append(part)
        hard = np.flatnonzero(~easy)
        lists = [e.ids for e in self._fast(forms.take(pa.array(hard)).to_pylist(), add_special_tokens=False)] if len(hard) else []
        lens[hard] = [len(x) for x in lists]
        chunks += [np.array(x, np.uint32) for x in lists]
        order = np.concatenate([*done, hard]).astype(np.int64)
        ids = np.concatenate(chunks) if chunks else np.zeros(0, np.uint32)
        at = np.empty(len(start), np.int64)
        at[order] = np.cumsum(lens[order]) - lens[order]
        return ids[gather(at, lens)], lens

    def _keep(self, raw: np.ndarray, h: np.ndarray, start: np.ndarray, size: np.ndarray, new: np.ndarray, alone: np.ndarray, ids: np.ndarray, at: np.ndarray, lens: np.ndarray) -> None:
        take = new[~alone[new] & (size[new] < 256)][: max(self._cached - len(self._hash), 0)]
        take = take[np.argsort(h[take])]
        where = np.searchsorted(self._hash, h[take])
        if len(self._hash):  # another form with the same hash stays
            free = self._hash[np.minimum(where, len(self._hash) - 1)] != h[take]
            take, where = take[free], where[free]
        if not len(take):
            return
        n, m = size[take], lens[take]
        put = lambda old, x: np.insert(old, where, x.astype(old.dtype))
        self._from = put(self._from, len(self._bytes) + np.cumsum(n) - n)
        self._at = put(self._at, len(self._ids) + np.cumsum(m) - m)
        self._hash, self._size, self._len = put(self._hash, h[take]), put(self._size, n), put(self._len, m)
        self._bytes = np.concatenate([self._bytes, raw[gather(start[take], n)]])
        self._ids = np.concatenate([self._ids, ids[gather(at[take], m)]])


def _strings(raw: np.ndarray, size: np.ndarray) -> pa.Array:
    """Strings of the given sizes, one after another in ``raw``."""
    offsets = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
    return pa.Array.from_buffers(pa.large_string(), len(size), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(raw))])


_encoders: dict[str, ExactEncoder] = {}


def encoder(path: str) -> ExactEncoder:
    if path not in _encoders:
        _encoders[path] = ExactEncoder(path)
    return _encoders[path]


# --------------------------------------------------------------------------- shingles
def shingles(h: np.ndarray, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, start) of the ``width``-word shingles of texts, by word hashes ``h`` and the
    texts' first words: a text of fewer words, but at least one, is one shingle as a whole.
    ``start`` has, for each text, the index of its first shingle (one entry more than texts)."""
    n = np.diff(first)
    count = np.where(n >= width, n - width + 1, (n > 0).astype(np.int64))
    start = np.concatenate([[0], np.cumsum(count)]).astype(np.int64)
    at = gather(first[:-1], count)
    size = np.repeat(np.minimum(n, width), count)
    out = np.zeros(len(at), np.uint64)
    for k in range(width):
        has = size > k
        word = h[np.minimum(at + k, max(len(h) - 1, 0))] if len(h) else out
        out = np.where(has, mix(out * np.uint64(0x9E3779B97F4A7C15) + word + np.uint64(k + 1)), out)
    return out, start


def distinct(h: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes of each text, in ascending order within it."""
    owner = np.repeat(np.arange(len(start) - 1), np.diff(start))
    order = np.lexsort((h, owner))
    h, owner = h[order], owner[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    return h[new], np.concatenate([[0], np.cumsum(np.bincount(owner[new], minlength=len(start) - 1))]).astype(np.int64)


# --------------------------------------------------------------------------- fixed-size filters
FILTER_BITS = 1 << 23


def key_filter(keys: DataFrame, column: str) -> np.ndarray:
    """Bitmap of hashed long keys, of a fixed 1 MB whatever the table's size.  It only spares work:
    an exact join must follow."""
    from pyspark.sql import functions as F

    bit = F.pmod(F.col(column), F.lit(FILTER_BITS))
    maps = keys.select(bit.alias("bit")).groupBy((F.col("bit") / 32768).cast("int").alias("bucket")).agg(F.bitmap_construct_agg(F.col("bit") % 32768).alias("bits")).collect()
    out = np.zeros(FILTER_BITS // 8, np.uint8)
    for bucket, bits in maps:
        out[bucket * 4096 : (bucket + 1) * 4096] = np.frombuffer(bytes(bits), np.uint8)
    return out


def in_filter(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which int64 keys may be in the set of :func:`key_filter`."""
    bit = np.mod(keys, FILTER_BITS)
    return bits[bit >> 3] >> (bit & 7).astype(np.uint8) & 1 != 0
