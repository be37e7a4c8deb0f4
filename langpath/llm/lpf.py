"""Removal of long repeated byte strings by longest-previous-factor values over all documents.

A position's longest previous factor (LPF) is the length of the longest string that starts there and
also at an earlier position; it follows from the previous and the next smaller position in suffix
order (:func:`lpf_array` does so for one text).  To remove repeats of ``LENGTH`` bytes it is enough to
know where LPF >= LENGTH, so the order of suffixes is needed to that depth only, and only among
suffixes that can share so long a string.

1. Winnowing picks anchors: in each run of ``LENGTH`` bytes the ``GRAM``-byte string of least hash, the leftmost
   of equals.  Equal strings of LENGTH bytes have equal anchors at the same place, so a position, which belongs to
   the one anchor of its run, can only match positions of anchors with the same hash.  Anchors seen once are done.
2. The other anchors bring their context: the bytes of the runs they own.  Equal contexts become one, with a count.
3. Contexts of one anchor hash meet, and their suffixes are put in order to depth LENGTH by prefix doubling over their bytes.
   Suffixes equal to that depth stand together by position, so the previous smaller position of each but the first is
   its neighbour there and LPF >= LENGTH; the first has no earlier match so long and is the one to keep.  Only groups of
   over ``HOT`` contexts have no suffix order: they are split by the 64-bit hash of the LENGTH bytes.

The same is done at a second depth, ``PASSAGE`` bytes, to find passages: the longest stretches made of strings of that length
that occur elsewhere, if they hold more than ``PASSAGE_WORDS`` words.  They are reported, not removed, and told by the 64-bit
hash of the strings instead of a suffix order, which would cost five times as much.

Texts that equal others as a whole take part once.  ``keep="first"`` removes later copies only; ``keep="none"`` removes
all occurrences, the first included.

Defined cases: a null text is empty; texts shorter than LENGTH lose nothing; repeated rows are copies of each
other; an empty table gives no rows; matches never cross documents; other columns are ignored.  The first occurrence is the one
with the smallest (doc_id, position), a null doc_id last.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

LENGTH, GRAM, HOT = 400, 96, 32_768
PASSAGE, PASSAGE_WORDS = 200, 50
SEGMENT = 4 << 20
EMPTY_SHA = hashlib.sha256(b"").hexdigest()
NO_ID = (1 << 63) - 1


# --------------------------------------------------------------------------- one text
def suffix_array(text: bytes) -> np.ndarray:
    """Suffix order by prefix doubling."""
    n = len(text)
    rank = np.frombuffer(text, np.uint8).astype(np.int64) + 1
    width, order = 1, np.argsort(rank, kind="stable")
    while n:
        second = np.zeros(n, np.int64)
        second[: n - width] = rank[width:] if width < n else second[:0]
        order = np.lexsort((second, rank))
        new = (np.diff(rank[order]) != 0) | (np.diff(second[order]) != 0)
        rank[order] = np.concatenate([[1], 1 + np.cumsum(new)])
        width *= 2
        if rank.max() == n or width >= n:
            break
    return order


def lpf_array(text: bytes) -> np.ndarray:
    """Longest previous factor at each position, from previous and next smaller positions."""
    n, order = len(text), suffix_array(text).tolist()
    before, after = [-1] * n, [-1] * n
    stack: list[int] = []
    for p in order:
        while stack and stack[-1] > p:
            after[stack.pop()] = p
        before[p] = stack[-1] if stack else -1
        stack.append(p)

    def common_length(a: int, b: int, k: int) -> int:
        while b + k < n and text[a + k] == text[b + k]:
            k += 1
        return k

    out, left, right = np.zeros(n, np.int64), 0, 0
    for i in range(n):
        left = common_length(before[i], i, max(left - 1, 0)) if before[i] >= 0 else 0
        right = common_length(after[i], i, max(right - 1, 0)) if after[i] >= 0 else 0
        out[i] = max(left, right)
    return out


# --------------------------------------------------------------------------- anchors
def anchors(raw: np.ndarray, off: np.ndarray, lengths: tuple[int, ...], gram: int = GRAM) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length (hash, first run, last run) of the anchors of concatenated texts, in order: the anchor belongs to the
    runs of so many bytes that start at first..last; no run leaves its text.  Hashes of two lengths never meet."""
    found: list[list[tuple]] = [[] for _ in lengths]
    size = np.diff(off)
    for a in range(0, max(len(raw) - min(lengths) + 1, 0), SEGMENT):
        part = raw[a : min(a + SEGMENT + max(lengths) - 1, len(raw))]
        at = np.arange(len(part) - gram + 1)
        h = common.range_hash(common.prefix_hash(part), at, at + gram)
        v = (h & ~np.uint64((1 << 24) - 1)) | at.astype(np.uint64)
        for k, length in enumerate(lengths):
            runs, width = min(SEGMENT, len(part) - length + 1), length - gram + 1
            # the runs inside their texts
            begin, end = np.maximum(off[:-1] - a, 0), np.minimum(off[1:] - a - length + 1, runs)
            inside = common.gather(begin, np.maximum(end - begin, 0) * (size >= length))
            if not len(inside):
                continue
            use = v[: runs + width - 1]
            grid = np.concatenate([use, np.full(-len(use) % width, np.uint64((1 << 64) - 1))]).reshape(-1, width)
            fore = np.minimum.accumulate(grid, axis=1).reshape(-1)
            back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].reshape(-1)
            pos = (np.minimum(back[inside], fore[inside + width - 1]) & np.uint64((1 << 24) - 1)).astype(np.int64)
            cut = np.concatenate([[0], np.flatnonzero((np.diff(pos) != 0) | (np.diff(inside) != 1)) + 1])
            last = np.concatenate([cut[1:], [len(pos)]]) - 1
            named = common.mix(h[pos[cut]] + np.uint64(length)).view(np.int64)
            found[k].append((named, inside[cut] + a, inside[last] + a))
    none = (np.zeros(0, np.int64),) * 3
    return [tuple(np.concatenate(x) for x in zip(*f, strict=True)) if f else none for f in found]


def _class(raw: bytes) -> tuple[int, str]:
    digest = hashlib.sha256(raw)
    return int.from_bytes(digest.digest()[:8], "little", signed=True), digest.hexdigest()


def _texts(batch: pa.RecordBatch) -> list[bytes]:
    raw, off = common.flat_text(batch.column("text"))
    blob = raw.tobytes()
    return [blob[a:b] for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]


def _first_pass(docs: DataFrame, lengths: tuple[int, ...], gram: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "text"):
            texts = _texts(batch)
            names = [_class(t) for t in texts]
            raw, off = common.flat_text(batch.column("text"))
            found = anchors(raw, off, lengths, gram)
            h, owner = np.concatenate([x[0] for x in found]), np.concatenate([np.searchsorted(off, x[1], side="right") - 1 for x in found])
            start = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=len(texts)))]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(start), pa.array(h[np.argsort(owner, kind="stable")]))
            words = pa.array([len(t.split()) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(off)), words, pa.array([x[0] for x in names], pa.int64()), pa.array([x[1] for x in names]), lists], ["doc_id", "n_bytes", "n_words", "class", "sha", "anchors"])

    return docs.mapInArrow(run, "doc_id long, n_bytes long, n_words long, class long, sha string, anchors array<long>")


def _texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """Texts of the wanted classes, one document each, with their repeated anchors."""
    bits = docs.sparkSession.sparkContext.broadcast(common.key_filter(wanted, "class"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "text"):
            texts = _texts(batch)
            cls = np.array([_class(t)[0] for t in texts], np.int64)
            some = np.flatnonzero(common.in_filter(bits.value, cls))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(some)), pa.array(cls[some]), pa.array([texts[i] for i in some.tolist()], pa.binary())], ["doc_id", "class", "bytes"])

    found = docs.mapInArrow(run, "doc_id long, class long, bytes binary")
    want = wanted.select(F.col("class").alias("c"), F.col("who").alias("w"), "repeated")
    hit = found.join(want, [found["class"] == F.col("c"), found["doc_id"].eqNullSafe(F.col("w"))]).select("class", F.coalesce("w", F.lit(NO_ID)).alias("who"), "bytes", "repeated")
    return hit.dropDuplicates(["class"])


def _contexts(texts: DataFrame, lengths: tuple[int, ...], gram: int) -> DataFrame:
    """One row per repeated anchor: its depth and hash, its context and where its runs start."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "bytes"):
            raw, off = common.flat_text(batch.column("bytes").cast(pa.large_binary()))
            blob = raw.tobytes()
            cls, who = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("class", "who"))
            # whether a hash is repeated does not depend on the text it stands in
            wanted = np.unique(batch.column("repeated").flatten().to_numpy(zero_copy_only=False))
            for length, (h, lo, hi) in zip(lengths, anchors(raw, off, lengths, gram), strict=True):
                some = np.flatnonzero(np.isin(h, wanted))
                h, lo, hi = h[some], lo[some], hi[some]
                owner = np.searchsorted(off, lo, side="right") - 1
                for k in range(0, len(some), 4096):
                    a, b = lo[k : k + 4096], hi[k : k + 4096]
                    parts = [blob[x:y] for x, y in zip(a.tolist(), (b + length).tolist(), strict=True)]
                    ctx = [int.from_bytes(hashlib.blake2b(x, digest_size=8).digest(), "little", signed=True) for x in parts]
                    own = owner[k : k + 4096]
                    cols = [np.full(len(a), length, np.int32), h[k : k + 4096], np.array(ctx, np.int64), cls[own], who[own], a - off[own], b - a + 1]
                    yield pa.RecordBatch.from_arrays([*map(pa.array, cols), pa.array(parts, pa.binary())], ["depth", "hash", "ctx", "class", "who", "first_run", "n_runs", "part"])

    return texts.select("class", "who", "bytes", "repeated").mapInArrow(run, "depth int, hash long, ctx long, class long, who long, first_run long, n_runs long, part binary")


SPANS = "array<struct<at:int,n:int,who:bigint,pos:bigint>>"


def _run_hashes(parts: list[bytes], n_runs: np.ndarray, length: int) -> np.ndarray:
    """Hashes of all runs of the contexts, in order, in slices of bounded size."""
    out, k = [], 0
    sizes = np.array([len(p) for p in parts], np.int64)
    part_of = (np.cumsum(sizes) - sizes) // common.SLICE_BYTES
    for s in np.unique(part_of).tolist():
        pick = np.flatnonzero(part_of == s)
        raw = np.frombuffer(b"".join(parts[i] for i in pick.tolist()), np.uint8)
        begin = np.cumsum(sizes[pick]) - sizes[pick]
        at = common.gather(begin, n_runs[pick])
        out.append(common.range_hash(common.prefix_hash(raw), at, at + length))
        k += len(pick)
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def suffix_ranks(raw: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
    """Rank of the suffixes that start at ``at`` among each other, in order of their first ``length`` bytes; equal ones
    share a rank.  As in prefix doubling, neighbouring ranks, two or three, make the rank of a multiple of the depth."""
    width = min(8, length)
    padded = np.concatenate([raw, np.zeros(length, np.uint8)]).astype(np.uint64)
    key = np.zeros(len(raw), np.uint64)
    for k in range(width):
        key = (key << np.uint64(8)) | padded[k : k + len(raw)]
    del padded
    while width < length:
        rank = _dense_ranks(key)
        top = int(rank.max(initial=0)) + 2
        key, last = rank, 0
        for k in (1, 2) if top**3 < 1 << 63 else (1,):  # ranks of neighbours, as many as a key holds
            step = min(k * width, length - width)
            if step > last:
                nxt = np.zeros(len(raw), np.int64)
                nxt[: max(len(raw) - step, 0)] = rank[step:] + 1
                key, last = key * top + nxt, step
        width += last
    return _dense_ranks(key[at])


def _dense_ranks(key: np.ndarray) -> np.ndarray:
    order = np.argsort(key)
    key = key[order]
    new = np.zeros(len(key), np.int64)
    new[1:] = key[1:] != key[:-1]
    rank = np.empty(len(key), np.int64)
    rank[order] = np.cumsum(new)
    return rank


def repeated_runs(h: np.ndarray, n_runs: np.ndarray, weight: np.ndarray, who: np.ndarray, first_run: np.ndarray):
    """Per run, by its suffix rank ``h`` to depth LENGTH: whether it occurs again, and its first occurrence."""
    ctx = np.repeat(np.arange(len(n_runs)), n_runs)
    pos = common.gather(first_run, n_runs)
    order = np.lexsort((pos, who[ctx], h))  # equal suffixes by position: the one before is the previous smaller
    ho = h[order]
    new = np.ones(len(ho), bool)
    new[1:] = ho[1:] != ho[:-1]
    group = np.cumsum(new) - 1
    total = np.bincount(group, weights=weight[ctx[order]]) if len(ho) else np.zeros(0)
    lead = order[new][group] if len(ho) else order
    again, first = np.zeros(len(h), bool), np.zeros(len(h), np.int64)
    again[order] = total[group] > 1
    first[order] = lead
    return ctx, again, who[ctx[first]], pos[first]


def _spans(n_runs: np.ndarray, again: np.ndarray, who: np.ndarray, pos: np.ndarray) -> list[list[dict]]:
    """Per context the repeated stretches: start, runs, and where the first occurrence stands."""
    begin = np.cumsum(n_runs) - n_runs
    edge = np.zeros(len(again) + 1, bool)
    edge[begin] = True
    if len(again):
        edge[1:-1] |= (again[1:] != again[:-1]) | (who[1:] != who[:-1]) | (pos[1:] != pos[:-1] + 1)
        edge[-1] = True
    cut = np.flatnonzero(edge)
    out: list[list[dict]] = [[] for _ in n_runs]
    home = np.searchsorted(begin, cut[:-1], side="right") - 1 if len(cut) else cut
    for a, b, k in zip(cut[:-1].tolist(), cut[1:].tolist(), home.tolist(), strict=True):
        if again[a]:
            out[k].append({"at": a - int(begin[k]), "n": b - a, "who": int(who[a]), "pos": int(pos[a])})
    return out


def _judge(distinct: DataFrame, length: int) -> DataFrame:
    """(hash, ctx, spans) of contexts; all contexts of a hash stand in one partition, in a row.  ``length`` is the depth
    to which suffixes are ordered."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def flush(rows: list[tuple]) -> pa.RecordBatch:
            depth, h, ctx, m, who, first, n, parts = zip(*rows, strict=True)
            n = np.array(n, np.int64)
            size_of = np.array([len(x) for x in parts], np.int64)
            at = common.gather(np.cumsum(size_of) - size_of, n)
            if depth[0] == length:
                ranks = suffix_ranks(np.frombuffer(b"".join(parts), np.uint8), at, length)
            else:  # passages are reported only: equal strings are told by their hash
                ranks = _run_hashes(parts, n, depth[0])
            _, again, w, p = repeated_runs(ranks, n, np.array(m, np.int64), np.array(who, np.int64), np.array(first, np.int64))
            return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(ctx, pa.int64()), pa.array(_spans(n, again, w, p), pa.list_(pa.struct([("at", pa.int32()), ("n", pa.int32()), ("who", pa.int64()), ("pos", pa.int64())])))], ["hash", "ctx", "spans"])

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and (row[0] != held[-1][0] or (size > common.SLICE_BYTES and row[1] != held[-1][1])):
                    yield flush(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[-1])
        if held:
            yield flush(held)

    return distinct.select("depth", "hash", "ctx", "m", "who", "first_run", "n_runs", "part").mapInArrow(run, f"hash long, ctx long, spans {SPANS}")


def _judge_hot(distinct: DataFrame, length: int) -> DataFrame:
    """The same for anchors with very many contexts: runs are dealt by their own hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "part"):
            n = batch.column("n_runs").to_numpy(zero_copy_only=False)
            h = _run_hashes(batch.column("part").to_pylist(), n, length).view(np.int64)
            at = common.gather(np.zeros(len(n), np.int64), n)
            cols = [np.repeat(batch.column(c).to_numpy(zero_copy_only=False), n) for c in ("hash", "ctx", "m", "who", "first_run")]
            yield pa.RecordBatch.from_arrays([*map(pa.array, cols), pa.array(at), pa.array(h)], ["hash", "ctx", "m", "who", "first_run", "at", "run"])

    runs = distinct.select("hash", "ctx", "m", "who", "first_run", "n_runs", "part").mapInArrow(run, "hash long, ctx long, m long, who long, first_run long, at long, run long")
    many = runs.groupBy("run").agg(F.sum("m").alias("total"), F.min(F.struct("who", (F.col("first_run") + F.col("at")).alias("pos"))).alias("first")).where("total > 1")
    hit = runs.join(many, "run").select("hash", "ctx", F.struct(F.col("at").cast("int").alias("at"), F.lit(1).alias("n"), F.col("first.who").alias("who"), F.col("first.pos").alias("pos")).alias("s"))
    return hit.groupBy("hash", "ctx").agg(F.collect_list("s").alias("spans"))


# --------------------------------------------------------------------------- the operator
def remove_repeats(
    docs: DataFrame, length: int = LENGTH, gram: int = GRAM, keep: str = "first", with_text: bool = False, doc_id: str = "doc_id", text: str = "text", passage: tuple[int, int] | None = None
) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256, removed spans (start, end), passages (start, end), and the
    rest itself with ``with_text`` (null if nothing was removed: the text stays as it is).  ``passage``: bytes and words
    of what is reported as a passage; without it there are none."""
    if keep not in ("first", "none"):
        raise ValueError("keep is 'first' or 'none'")
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    depths = (length, passage[0]) if passage else (length,)
    rows = common.cut(_first_pass(src, depths, gram), "lpf-rows")
    classes = common.cut(rows.groupBy("class").agg(F.min("doc_id").alias("who"), F.count("*").alias("copies"), F.first("n_words").alias("n_words"), F.first("anchors").alias("anchors")), "lpf-classes")
    each = classes.select("class", F.explode("anchors").alias("hash"))
    # a table of its own: an anchor that very many texts share is then split where both meet
    twice = common.cut(each.groupBy("hash").agg(F.count("*").alias("c")).where("c > 1").select("hash"), "lpf-twice")
    shared = each.join(twice, "hash").groupBy("class").agg(F.collect_set("hash").alias("repeated"))
    wanted = common.cut(classes.select("class", "who").join(shared, "class"), "lpf-wanted")
    # from here on nobody asks for the anchors of all texts
    heads = common.cut(classes.select("class", "who", "copies", "n_words"), "lpf-heads")
    lines = common.cut(rows.select("doc_id", "n_bytes", "class", "sha"), "lpf-lines")
    common.drop_cut(rows, classes, twice)
    texts = common.cut(_texts_of(src, wanted), "lpf-texts")
    common.drop_cut(wanted)

    ctx = common.cut(_contexts(texts, depths, gram), "lpf-contexts")
    order = F.struct("who", "first_run")
    distinct = ctx.groupBy("hash", "ctx").agg(F.first("depth").alias("depth"), F.count("*").alias("m"), F.min(order).alias("o"), F.first("n_runs").alias("n_runs"), F.first("part").alias("part")).select("depth", "hash", "ctx", "m", F.col("o.who").alias("who"), F.col("o.first_run").alias("first_run"), "n_runs", "part")
    distinct = common.cut(distinct, "lpf-distinct")
    crowd = distinct.groupBy("hash").agg(F.count("*").alias("c"))
    hot = crowd.where(F.col("c") > HOT).select("hash")
    cool = distinct.join(F.broadcast(hot), "hash", "left_anti") if hot.limit(1).count() else distinct
    found = _judge(cool.repartition(parts, "hash").sortWithinPartitions("depth", "hash", "ctx"), length)
    if cool is not distinct:
        for depth in depths:
            found = found.unionByName(_judge_hot(distinct.where(F.col("depth") == depth).join(F.broadcast(hot), "hash"), depth))
    found = common.cut(found.where(F.size("spans") > 0), "lpf-found")
    s = F.col("s")
    hit = ctx.select("depth", "hash", "ctx", "class", "who", "first_run").join(found, ["hash", "ctx"]).select("depth", "class", F.col("who").alias("own"), "first_run", F.explode("spans").alias("s"))
    if keep == "first":
        hit = hit.where((F.col("depth") != length) | ~((s["who"] == F.col("own")) & (s["pos"] == F.col("first_run") + s["at"])))
    reach = F.struct((F.col("depth") != length).alias("p"), (F.col("first_run") + s["at"]).alias("a"), (F.col("first_run") + s["at"] + s["n"] + (F.col("depth") - 1)).alias("b"))
    spans = hit.select("class", reach.alias("r")).groupBy("class").agg(F.collect_list("r").alias("spans"))
    cut_rows = common.cut(_apply(texts.select("class", "bytes").join(spans, "class"), with_text, passage[1] if passage else 0), "lpf-cut")
    common.drop_cut(texts, ctx, distinct, found)

    info = heads.select("class", F.col("who").alias("first_doc"), "copies", "n_words").join(cut_rows, "class", "left")
    out = lines.join(info, "class")
    copied = (F.col("copies") > 1) & (F.col("n_bytes") >= length)
    if keep == "first":
        # of whole copies the first stays, but for what it repeats of others
        copied = copied & (F.coalesce("doc_id", F.lit(NO_ID)) != F.coalesce("first_doc", F.lit(NO_ID)))
    whole = F.array(F.struct(F.lit(0).cast("long").alias("a"), F.col("n_bytes").alias("b")))
    none = F.array().cast("array<struct<a:bigint,b:bigint>>")
    long = (F.col("copies") > 1) & (F.col("n_bytes") >= passage[0]) & (F.col("n_words") > passage[1]) if passage else F.lit(False)
    pick = lambda all_, part, none: F.when(copied, all_).otherwise(F.coalesce(part, none))
    cols = [
        "doc_id",
        "n_bytes",
        pick(F.col("n_bytes"), F.col("n_removed"), F.lit(0).cast("long")).alias("n_removed"),
        pick(F.lit(1).cast("long"), F.col("n_spans"), F.lit(0).cast("long")).alias("n_spans"),
        pick(F.lit(EMPTY_SHA), F.col("kept_sha256"), F.col("sha")).alias("kept_sha256"),
        pick(whole, F.col("removed"), none).alias("removed"),
        F.when(long, whole).otherwise(F.coalesce("passages", none)).alias("passages"),
    ]
    if with_text:
        cols.append(F.when(copied, F.lit(b"")).otherwise(F.col("kept")).alias("kept"))
    return out.select(*cols)


def _merged(spans: Iterator[tuple[int, int]]) -> list[list[int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


def _apply(texts: DataFrame, with_text: bool, words: int) -> DataFrame:
    """Merge each text's spans and take them out; passages are the merged ones of over ``words`` words."""
    span = "array<struct<a:bigint,b:bigint>>"
    schema = f"class long, n_removed long, n_spans long, kept_sha256 string, removed {span}, passages {span}" + ", kept binary" * with_text
    names = ["class", "n_removed", "n_spans", "kept_sha256", "removed", "passages"] + ["kept"] * with_text
    ends = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), ends, ends] + [pa.binary()] * with_text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "bytes"):
            cols: list[list] = [[] for _ in names]
            for cls, raw, spans in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                gone = _merged((s["a"], s["b"]) for s in spans if not s["p"])
                edges = [0, *(x for m in gone for x in m), len(raw)]
                rest = b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True))
                said = [{"a": a, "b": b} for a, b in _merged((s["a"], s["b"]) for s in spans if s["p"]) if len(raw[a:b].split()) > words]
                row = [cls, len(raw) - len(rest), len(gone), hashlib.sha256(rest).hexdigest(), [{"a": a, "b": b} for a, b in gone], said, rest]
                for c, v in zip(cols, row, strict=False):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

    return texts.mapInArrow(run, schema)
