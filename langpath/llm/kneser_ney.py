"""Quality classifier: interpolated modified Kneser-Ney n-grams over subword tokens.

Trusted texts (labelled of good quality) train the model: all of them, whole.  Texts are encoded by the
byte-level vocabulary, so every script has its own tokens, and 3-grams of tokens are counted per slice, then
summed, sharded by gram.  A gram is packed exactly into one long.  Lower orders hold continuation counts.
Joins of the sharded count tables (gram with its context's totals, gram with the probability of its
suffix) give each seen gram its interpolated probability and each context its back-off weight.

Documents are scored by sharded joins too.  Texts are kept as slices of encoded tokens.  A slice asks for each of its
distinct grams once, in one block per shard of the count tables; blocks meet the shard's probabilities and back-off
weights, and the slice sums the answers over its texts.  So what is shuffled grows with the distinct grams of slices, not
with the tokens.  Only tables with at most one entry per token of the vocabulary are broadcast.  Costs are summed as
integers, so equal texts score equally.

Documents are in two folds.  A document is scored by the model of the other fold's trusted texts, so no
text is judged by a model that has read it, and the trusted documents' scores show what good text unseen by the
model gets.  A document's perplexity (per byte) is held against a quantile of the trusted documents of its language.

``fit``, ``table`` and ``dense`` give the same interpolation over ``CLASSES`` = 64 byte classes, a model small enough to be
summed up whole; no query uses it.

Defined cases: null or empty texts have no perplexity and are not kept; documents of a language without trusted texts
use the quantile over all; a null language is a language; repeated rows get equal scores; without any trusted text all
with a perplexity are kept; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

ORDER, CLASSES = 4, 64
QUANTILE = 0.995
BEGIN, END = 0, 1
# tokens: grams of TOKENS, BITS bits each, and above them the fold of the texts they are counted in
TOKENS, BITS = 3, 20
FOLD = 1 << TOKENS * BITS
UNIT = 1 << 10  # costs are counted in so many parts of a bit
MISSING = 0xFFFF  # the answer for a gram without entry
#: A slice ends after so many bytes of text; a shard has about so many tokens' grams and so many entries of the model.
SLICE_TEXT, SHARD_TOKENS, SHARD_ENTRIES = 8 << 20, 1 << 22, 1 << 20
#: Training counts are summed over so many grams at a time before they are shuffled.
SUMMED = 1 << 21
#: Slices are scored in so many rounds, each of which shuffles its share of the encoded texts.
ROUNDS = 4
ENCODED = 1 << 20  # bytes of text that are encoded at a time
PIECE = 1 << 18  # grams that a step with temporary arrays handles at a time


def _classes() -> np.ndarray:
    out = np.full(256, 59, np.uint8)  # other signs
    out[0x20], out[[*range(0x00, 0x20), 0x7F]] = 2, 3
    out[ord("a") : ord("z") + 1] = np.arange(4, 30)
    out[ord("A") : ord("Z") + 1] = np.arange(30, 56)
    out[ord("0") : ord("9") + 1] = 56
    out[[ord(c) for c in ".,"]] = 57
    out[[ord(c) for c in ";:!?'\"()-"]] = 58
    out[0xC0:] = 60
    out[0x80:0xC0] = 61 + np.arange(64) % 3
    return out


_CLASS = _classes()


def grams(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(4-gram codes, first): the grams of each text, with ORDER - 1 begin marks and one end mark."""
    n = np.diff(off)
    size = n + ORDER  # marks included
    begin = np.cumsum(size) - size
    seq = np.zeros(int(size.sum()), np.int32)
    seq[common.gather(begin + ORDER - 1, n)] = _CLASS[raw]
    seq[begin + size - 1] = END
    code = np.zeros(max(len(seq) - ORDER + 1, 0), np.int32)
    for k in range(ORDER):
        code = code * CLASSES + seq[k : len(seq) - ORDER + 1 + k]
    count = n + 1
    return code[common.gather(begin, count)], np.concatenate([[0], np.cumsum(count)])


def count_grams(texts: DataFrame) -> DataFrame:
    """(gram, c) of all texts; each task sums its own before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CLASSES**ORDER, np.int64)
        for batch in common.slices(batches, "text"):
            raw, off = common.flat_text(batch.column("text"))
            keep = np.diff(off) > 0
            code, _ = grams(raw, np.concatenate([off[:-1][keep], off[-1:]]))
            total += np.bincount(code, minlength=len(total))
        seen = np.flatnonzero(total)
        for a in range(0, len(seen), 1 << 16):
            part = seen[a : a + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(total[part])], ["gram", "c"])

    return texts.select("text").mapInArrow(run, "gram long, c long").groupBy("gram").agg(F.sum("c").alias("c"))


def discounts(counts: DataFrame) -> tuple[float, float, float]:
    """Modified discounts for counts of one, two and three or more."""
    n = dict.fromkeys((1, 2, 3, 4), 0) | {r[0]: r[1] for r in counts.where("c <= 4").groupBy("c").count().collect()}
    if not all(n.values()):
        return 0.5, 0.75, 0.9
    y = n[1] / (n[1] + 2 * n[2])
    return tuple(min(max(k - (k + 1) * y * n[k + 1] / n[k], 0.05), k - 0.05) for k in (1, 2, 3))


def fit(texts: DataFrame) -> list[tuple[DataFrame, DataFrame]]:
    """For orders 1 to ORDER over byte classes: (gram, p) of seen grams and (context, back-off weight)."""
    return interpolate(count_grams(texts), ORDER, CLASSES, lambda g: F.floor(g / CLASSES), lambda g, n: g % CLASSES**n)


def interpolate(top: DataFrame, order: int, size: int, context: Callable[[Column], Column], suffix: Callable[[Column, int], Column], made: list[DataFrame] | None = None) -> list[tuple[DataFrame, DataFrame]]:
    """For orders 1 to ``order``: (gram, p) of seen grams and (context, back-off weight w), from (gram, c) of the highest;
    ``size`` is the number of symbols.  The tables that were written go into ``made``."""
    made = [] if made is None else made
    counts = [common.cut(top, "kn-counts")]
    for n in range(order - 1, 0, -1):
        # distinct left neighbours of the shorter gram
        counts.insert(0, common.cut(counts[0].groupBy(suffix(F.col("gram"), n).alias("gram")).agg(F.count("*").alias("c")), "kn-counts"))
    made += counts
    out: list[tuple[DataFrame, DataFrame]] = []
    lower = None
    for n, g in enumerate(counts, 1):
        d = discounts(g)
        cut = F.when(F.col("c") == 1, d[0]).when(F.col("c") == 2, d[1]).otherwise(d[2])
        row = g.select("gram", "c", cut.alias("d"), context(F.col("gram")).alias("context"))
        ctx = row.groupBy("context").agg(F.sum("c").alias("total"), F.sum("d").alias("mass"))
        joined = row.join(ctx, "context")
        if lower is None:
            tail = F.lit(1.0 / size)
        else:
            joined = joined.withColumn("suffix", suffix(F.col("gram"), n - 1)).join(lower.select(F.col("gram").alias("suffix"), F.col("p").alias("tail")), "suffix")
            tail = F.col("tail")
        p = joined.select("gram", ((F.col("c") - F.col("d") + F.col("mass") * tail) / F.col("total")).alias("p"))
        lower = common.cut(p, f"kn-order{n}")
        made.append(lower)
        out.append((lower, ctx.select("context", (F.col("mass") / F.col("total")).alias("w"))))
    return out


def table(model: list[tuple[DataFrame, DataFrame]]) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """The model on the driver: at most CLASSES**n entries for order n, by construction."""
    out = []
    for p, ctx in model:
        g, c = p.toPandas(), ctx.toPandas()
        out.append((g["gram"].to_numpy(np.int32), g["p"].to_numpy(np.float32), c["context"].to_numpy(np.int32), c["w"].to_numpy(np.float32)))
    return out


def dense(sparse: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
    """Log probability of every gram of the highest order, unseen ones by back-off."""
    p = np.full(1, 1.0 / CLASSES, np.float32)
    for n, (g, seen, context, weight) in enumerate(sparse, 1):
        w = np.ones(CLASSES ** (n - 1), np.float32)
        w[context] = weight
        # p has the grams of the order below; one more class stands in front of each
        suffix = np.tile(p, CLASSES) if n > 1 else np.full(CLASSES, p[0])
        p = np.repeat(w, CLASSES) * suffix
        p[g] = seen
    return np.log(np.maximum(p, 1e-12))


# --------------------------------------------------------------------------- tokens
def fold_of(doc_id: Column) -> Column:
    return F.pmod(F.xxhash64(doc_id), F.lit(2))


def suffix_of(gram: Column, n: int) -> Column:
    """The last n tokens of a gram, in its fold."""
    return gram.bitwiseAND(F.lit(FOLD | (1 << n * BITS) - 1))


def context_of(gram: Column) -> Column:
    """All tokens but the last, in the same fold."""
    return F.shiftright(gram.bitwiseAND(F.lit(FOLD - 1)), BITS).bitwiseOR(gram.bitwiseAND(F.lit(FOLD)))


def codes(ids: np.ndarray, n: np.ndarray, fold: np.ndarray) -> np.ndarray:
    """The n + 1 grams of each text, one text after another; ``n`` has the tokens of texts, none of them empty."""
    size = n + TOKENS
    end = np.cumsum(size)
    mark = np.zeros(int(size.sum()), bool)  # begin marks, and after each text its end
    mark[end - 1] = True
    for k in range(TOKENS - 1):
        mark[end - size + k] = True
    seq = np.full(len(mark), BEGIN, np.int32)
    seq[end - 1] = END
    np.logical_not(mark, out=mark)
    seq[mark] = ids
    seq[mark] += END + 1
    del mark
    whole = np.ones(max(len(seq) - TOKENS + 1, 0), bool)  # no gram spans two texts
    for k in range(1, TOKENS):
        whole[end[:-1] - k] = False
    code = np.zeros(int(whole.sum()), np.int64)
    for k in range(TOKENS):
        code <<= BITS
        code |= seq[k : len(whole) + k][whole]
    del seq, whole
    np.bitwise_or(code, FOLD, out=code, where=np.repeat(fold.astype(bool), n + 1))
    return code


def _distinct(x: np.ndarray) -> np.ndarray:
    """Distinct values in order; sorts ``x`` itself."""
    x.sort()
    new = np.ones(len(x), bool)
    new[1:] = x[1:] != x[:-1]
    return x[new]


def token_grams(texts: DataFrame, tokenizer: str) -> DataFrame:
    """(gram, n): how often each gram stands in a slice of the texts; ``texts`` has fold and text.  Empty texts have none."""

    def summed(held: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        gram, n = np.unique(np.concatenate(held), return_counts=True)
        for a in range(0, len(gram), 1 << 16):
            part = slice(a, a + (1 << 16))
            yield pa.RecordBatch.from_arrays([pa.array(gram[part]), pa.array(n[part])], ["gram", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = common.encoder(tokenizer)
        held: list[np.ndarray] = []
        for batch in common.slices(batches, "text", ENCODED, encoding=True):
            ids, off = enc.encode(batch.column("text"))
            keep = np.diff(off) > 0
            held.append(codes(ids, np.diff(off)[keep], batch.column("fold").to_numpy()[keep]))
            if sum(map(len, held)) >= SUMMED:
                yield from summed(held)
                held = []
                common.trim()
        if held:
            yield from summed(held)

    return texts.select("fold", "text").mapInArrow(run, "gram long, n long")


def vocabulary_size(tokenizer: str) -> int:
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer).get_vocab_size() + 1  # the end mark included


def fit_tokens(texts: DataFrame, tokenizer: str, made: list[DataFrame] | None = None) -> list[tuple[DataFrame, DataFrame]]:
    """The model of each fold; ``texts`` has fold and text."""
    top = token_grams(texts, tokenizer).groupBy("gram").agg(F.sum("n").alias("c"))
    return interpolate(top, TOKENS, vocabulary_size(tokenizer), context_of, suffix_of, made)


def gram_costs(grams_: DataFrame, model: list[tuple[DataFrame, DataFrame]], size: int) -> DataFrame:
    """(gram, cost): what each distinct gram of a table costs, in parts of a bit; unseen ones by back-off.  Whole corpora
    are scored by :func:`perplexities`, which sends blocks instead of rows."""
    out = grams_.select("gram").distinct().withColumn("p", F.lit(1.0 / size))
    for n, (seen, contexts) in enumerate(model, 1):
        # one entry per token at most up to here; beyond, the tables grow with the corpus
        small = {"gram": n == 1, "context": n <= 2}
        g = suffix_of(F.col("gram"), n)
        for key, table_, of in (("gram", seen, g), ("context", contexts, context_of(g))):
            other = table_.select(F.col(key).alias("at"), F.col({"gram": "p", "context": "w"}[key]).alias(f"new_{key}"))
            out = out.withColumn("here", of).join(other.hint("broadcast" if small[key] else "merge"), F.col("here") == F.col("at"), "left").drop("here", "at")
        p = F.coalesce("new_gram", F.coalesce("new_context", F.lit(1.0)) * F.col("p"))
        out = out.select("gram", p.alias("p"))
    return out.select("gram", F.round(-F.log2("p") * UNIT).cast("long").alias("cost"))


def _squeeze(x: np.ndarray, level: int = 3) -> bytes:
    """Numbers, byte by byte of equal weight."""
    return zstandard.ZstdCompressor(level).compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, x.itemsize).T).tobytes())


def _expand(data: bytes, dtype: type) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(np.dtype(dtype).itemsize, -1)
    return np.ascontiguousarray(planes.T).view(dtype).ravel()


def encoded_slices(docs: DataFrame, tokenizer: str) -> DataFrame:
    """One row per slice of documents: its number, its tokens, and of its documents doc_id, lang, n_bytes, fold, tokens and
    all ids.  Numbers are drawn, so the result must be written before it is used."""
    narrow = vocabulary_size(tokenizer) <= 1 << 16

    def packed(held: list[tuple]) -> pa.RecordBatch:
        ids, n, n_bytes, fold = (np.concatenate([h[k] for h in held]) for k in range(4))
        one = lambda values: pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), values)
        texts = [one(pa.concat_arrays([h[k] for h in held])) for k in (4, 5)]
        numbers = [one(pa.array(x.astype(np.int64))) for x in (n_bytes, fold, n)]
        blob = zstandard.ZstdCompressor(3).compress(ids.tobytes())
        return pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().int >> 65], pa.int64()), pa.array([int(n.sum())], pa.int64()), *texts, *numbers, pa.array([blob], pa.binary())], ["slice", "tokens", "doc_id", "lang", "n_bytes", "fold", "n", "ids"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = common.encoder(tokenizer)
        held: list[tuple] = []
        for batch in common.slices(batches, "text", ENCODED, encoding=True):
            ids, off = enc.encode(batch.column("text"))
            n_bytes = np.diff(common.flat_text(batch.column("text"))[1])
            held.append((ids.astype(np.uint16 if narrow else np.uint32), np.diff(off), n_bytes, batch.column("fold").to_numpy(), batch.column("doc_id"), batch.column("lang")))
            if sum(int(h[2].sum()) for h in held) >= SLICE_TEXT:
                yield packed(held)
                held = []
                common.trim()
        if held:
            yield packed(held)

    schema = "slice long, tokens long, doc_id array<long>, lang array<string>, n_bytes array<long>, fold array<long>, n array<long>, ids binary"
    return docs.select("doc_id", "lang", "fold", "text").mapInArrow(run, schema)


def _grams_of(row: dict, narrow: bool) -> tuple[np.ndarray, np.ndarray]:
    """(grams of all texts of a slice, tokens of its texts)."""
    ids = np.frombuffer(zstandard.ZstdDecompressor().decompress(row["ids"]), np.uint16 if narrow else np.uint32)
    n = np.array(row["n"], np.int64)
    return codes(ids, n[n > 0], np.array(row["fold"], np.int64)[n > 0]), n


def _ends_of(gram: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The shorter grams that a gram's cost may need: its context and its suffix."""
    fold = gram & FOLD
    return (gram & (FOLD - 1)) >> BITS | fold, gram & ((1 << (TOKENS - 1) * BITS) - 1) | fold


def _lower_of(gram: np.ndarray) -> np.ndarray:
    """The distinct shorter grams that costs of these may need, in order."""
    n = len(gram)
    both = np.empty(2 * n, np.int64)
    both[:n], both[n:] = _ends_of(gram)
    return _distinct(both)


_MIX = (1640531527, 1013904223)  # below 2**31, so the sum of products stays below 2**53


def shard_of(gram: np.ndarray, shards: int) -> np.ndarray:
    """By all tokens but the last: a context's grams, at most one for each token of the vocabulary, stand together."""
    low = (1 << BITS) - 1
    return ((gram >> BITS & low) * _MIX[0] + (gram >> 2 * BITS) * _MIX[1] >> 12) % shards


def _dealt(gram: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order by shard, the shards that have grams, where each begins in that order); made piece by piece in narrow numbers."""
    shard = np.empty(len(gram), np.uint16 if shards <= 1 << 16 else np.int32)
    for a in range(0, len(gram), PIECE):
        shard[a : a + PIECE] = shard_of(gram[a : a + PIECE], shards)
    order = np.argsort(shard, kind="stable").astype(np.uint32 if len(gram) < 1 << 32 else np.int64)
    count = np.bincount(shard, minlength=shards)
    at = np.flatnonzero(count)
    return order, at, np.cumsum(count)[at] - count[at]


def shard_column(gram: Column, shards: int) -> Column:
    """The same as :func:`shard_of`."""
    mixed = F.shiftright(gram, BITS).bitwiseAND(F.lit((1 << BITS) - 1)) * _MIX[0] + F.shiftright(gram, 2 * BITS) * _MIX[1]
    return F.pmod(F.shiftright(mixed, 12), F.lit(shards).cast("long"))


def blocks_of(row: dict, shards: int, narrow: bool) -> pa.RecordBatch:
    """The questions of one slice."""
    gram = _distinct(_grams_of(row, narrow)[0])
    sizes, places, blocks = [], [], []
    for n in (TOKENS, TOKENS - 1):
        if n < TOKENS:
            gram = _lower_of(gram)
        order, at, start = _dealt(gram, shards)
        for k, a, b in zip(at.tolist(), start.tolist(), [*start[1:].tolist(), len(gram)], strict=True):
            sizes.append(n)
            places.append(k)
            blocks.append(_squeeze(np.diff(gram[order[a:b]], prepend=0)))
        del order
    slice_ = np.full(len(places), row["slice"], np.int64)
    return pa.RecordBatch.from_arrays([pa.array(slice_), pa.array(sizes, pa.int64()), pa.array(places, pa.int64()), pa.array(blocks, pa.binary())], ["slice", "n", "shard", "grams"])


def questions(slices: DataFrame, shards: int, narrow: bool) -> DataFrame:
    """(slice, n, shard, grams): the distinct grams of n tokens of each slice, a block for each shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.forget_encoders()
        for batch in batches:
            for i in range(batch.num_rows):
                yield blocks_of({c: batch.column(c)[i].as_py() for c in batch.schema.names}, shards, narrow)
                common.trim()

    return slices.select("slice", "fold", "n", "ids").mapInArrow(run, "slice long, n long, shard long, grams binary")


def model_entries(model: list[tuple[DataFrame, DataFrame]]) -> DataFrame:
    """(kind, gram, cost): probabilities of seen grams (kind: how many tokens) and, as kind 0, the back-off weights of contexts
    of the highest order, all as costs."""
    cost = lambda c: F.greatest(F.lit(0), F.least(F.round(-F.log2(c) * UNIT), F.lit(MISSING - 1))).cast("int").alias("cost")
    parts = [model[n - 1][0].select(F.lit(n).alias("kind"), "gram", cost("p")) for n in (TOKENS, TOKENS - 1)]
    parts.append(model[-1][1].select(F.lit(0).alias("kind"), F.col("context").alias("gram"), cost("w")))
    return functools.reduce(DataFrame.unionAll, parts)


def sorted_entries(entries: DataFrame, shards: int) -> DataFrame:
    """(shard, kind, grams, costs): the entries of a shard, in order of gram, one row for each kind."""

    def run(part: pa.Table) -> pa.Table:
        common.forget_encoders()
        shard, kind, gram, cost = (part.column(c).to_numpy() for c in ("shard", "kind", "gram", "cost"))
        rows = []
        for k in np.unique(kind).tolist():
            g, c = gram[kind == k], cost[kind == k].astype(np.uint16)
            order = np.argsort(g)
            rows.append((int(shard[0]), k, _squeeze(np.diff(g[order], prepend=0)), _squeeze(c[order])))
        return pa.table(dict(zip(("shard", "kind", "grams", "costs"), map(list, zip(*rows, strict=True)), strict=True)))

    return entries.withColumn("shard", shard_column(F.col("gram"), shards)).groupBy("shard").applyInArrow(run, "shard long, kind long, grams binary, costs binary")


def _meet(asked: pa.Table, entries: pa.Table) -> pa.Table:
    """Answers to a shard's blocks: costs in the order of the block's grams, for shorter ones the back-off weights after them."""
    common.forget_encoders()
    common.trim()
    nothing = np.zeros(0, np.int64), np.zeros(0, np.uint16)
    known = {row["kind"]: (np.cumsum(_expand(row["grams"], np.int64)), _expand(row["costs"], np.uint16)) for row in entries.to_pylist()}
    known = {k: (np.append(g, -1), np.append(c, np.uint16(MISSING))) for k in (TOKENS, TOKENS - 1, 0) for g, c in [known.get(k, nothing)]}  # no gram is negative

    def look(k: int, want: np.ndarray) -> np.ndarray:
        g, c = known[k]
        at = np.searchsorted(g[:-1], want)
        return np.where(g[at] == want, c[at], np.uint16(MISSING))

    out = []
    for n, block in zip(asked.column("n").to_pylist(), asked.column("grams").to_pylist(), strict=True):
        want = np.cumsum(_expand(block, np.int64))
        out.append(_squeeze(look(n, want) if n == TOKENS else np.concatenate([look(n, want), look(0, want)])))
    return pa.table({"slice": asked.column("slice"), "n": asked.column("n"), "shard": asked.column("shard"), "costs": pa.array(out, pa.binary())})


def small_costs(model: list[tuple[DataFrame, DataFrame]], size: int) -> tuple[np.ndarray, np.ndarray]:
    """By fold and token: the cost of a token alone and of backing off from it.  Each table has one entry per token at most."""
    start = {int(c): w for c, w in model[0][1].select("context", "w").collect()}
    alone = np.repeat([[start.get(fold * FOLD, 1.0) / size] for fold in (0, 1)], size + END + 2, axis=1)
    back = np.ones_like(alone)
    for out, frame in ((alone, model[0][0].select("gram", "p")), (back, model[1][1].select("context", "w"))):
        rows = frame.toPandas()
        at = rows.iloc[:, 0].to_numpy(np.int64)
        out[at >> TOKENS * BITS, at & ((1 << BITS) - 1)] = rows.iloc[:, 1].to_numpy(np.float64)
    return tuple(np.rint(-np.log2(x) * UNIT).astype(np.int64) for x in (alone, back))


def lookup_tables(model: list[tuple[DataFrame, DataFrame]], tokenizer: str) -> tuple[DataFrame, tuple[np.ndarray, np.ndarray]]:
    """What scoring needs of a model: the table of :func:`model_entries`, and :func:`small_costs`."""
    return common.cut(model_entries(model), "kn-entries"), small_costs(model, vocabulary_size(tokenizer))


def bits_of(one: dict, asked: list[int], blocks: list[bytes], small: tuple[np.ndarray, np.ndarray], shards: int, narrow: bool) -> pa.Table:
    """doc_id, lang, n_bytes and bits of the texts of one slice, from the answers in order of shard."""
    alone, back = small
    code, n = _grams_of(one, narrow)
    order = np.argsort(code).astype(np.uint32 if len(code) < 1 << 32 else np.int64)
    top = code[order]
    size = len(code)
    del code
    new = np.ones(size, bool)
    new[1:] = top[1:] != top[:-1]
    top = top[new]
    lower = _lower_of(top)
    put = {}
    for k, gram, width in ((TOKENS, top, 1), (TOKENS - 1, lower, 2)):
        at, _, _ = _dealt(gram, shards)
        put[k] = np.empty((width, len(gram)), np.int32)
        a = 0
        for b in (b for b, kind in zip(blocks, asked, strict=True) if kind == k):
            came = _expand(b, np.uint16).reshape(width, -1)
            if a + came.shape[1] <= len(gram):
                put[k][:, at[a : a + came.shape[1]]] = came
            a += came.shape[1]
        if a != len(gram):
            raise RuntimeError(f"slice {one['slice']}: {a} answers for {len(gram)} grams")
        del at
    seen, weight = put[TOKENS - 1]
    cost = put[TOKENS][0]
    low = (1 << BITS) - 1
    for a in range(0, len(lower), PIECE):
        gram, here = lower[a : a + PIECE], seen[a : a + PIECE]
        fold = gram >> TOKENS * BITS
        here[:] = np.where(here == MISSING, back[fold, gram >> BITS & low] + alone[fold, gram & low], here)
    weight[weight == MISSING] = 0
    for a in range(0, len(top), PIECE):
        here = cost[a : a + PIECE]
        context, suffix = _ends_of(top[a : a + PIECE])
        here[:] = np.where(here == MISSING, weight[np.searchsorted(lower, context)] + seen[np.searchsorted(lower, suffix)], here)
    del top, lower, put, seen, weight
    code = np.empty(size, np.int32)
    code[order] = np.repeat(cost, np.diff(np.append(np.flatnonzero(new), size)))  # each gram becomes its cost
    some = n > 0
    bits = np.zeros(len(n))
    if some.any():
        bits[some] = np.add.reduceat(code, np.cumsum(n[some] + 1) - n[some] - 1, dtype=np.int64) / UNIT
    return pa.table({"doc_id": pa.array(one["doc_id"], pa.int64()), "lang": pa.array(one["lang"], pa.string()), "n_bytes": pa.array(one["n_bytes"], pa.int64()), "bits": pa.array(bits, mask=~some)})


def perplexities(docs: DataFrame, tables: tuple[DataFrame, tuple[np.ndarray, np.ndarray]], tokenizer: str, shards: int | None = None) -> DataFrame:
    """doc_id, lang, n_bytes and perplexity of each document, by the model of the other fold (its ``lookup_tables``, deleted
    when used); the number of shards follows the tokens and the model's entries."""
    narrow = vocabulary_size(tokenizer) <= 1 << 16
    row = docs.select("doc_id", "lang", (1 - fold_of(F.col("doc_id"))).alias("fold"), F.coalesce("text", F.lit("")).alias("text"))
    entries, small = tables[0], docs.sparkSession.sparkContext.broadcast(tables[1])
    slices = common.cut(encoded_slices(row, tokenizer), "kn-slices")
    shards = shards or 1 + (slices.agg(F.sum("tokens")).first()[0] or 0) // SHARD_TOKENS + entries.count() // SHARD_ENTRIES
    held = common.cut(sorted_entries(entries, shards), "kn-shards")
    common.drop_cut(entries)

    def total(texts: pa.Table, got: pa.Table) -> pa.Table:
        common.forget_encoders()
        got = got.sort_by("shard")
        asked, blocks = (got.column(c).to_pylist() for c in ("n", "costs"))
        out = []
        for one in texts.to_pylist():
            out.append(bits_of(one, asked, blocks, small.value, shards, narrow))
            common.trim()
        return pa.concat_tables(out) if out else none

    none = pa.table({"doc_id": pa.array([], pa.int64()), "lang": pa.array([], pa.string()), "n_bytes": pa.array([], pa.int64()), "bits": pa.array([], pa.float64())})
    rounds = []
    for k in range(ROUNDS):
        share = slices.where(F.pmod("slice", F.lit(ROUNDS)) == k)
        met = questions(share, shards, narrow).groupBy("shard").cogroup(held.groupBy("shard")).applyInArrow(_meet, "slice long, n long, shard long, costs binary")
        answers = common.cut(met, "kn-answers")
        scores = share.groupBy("slice").cogroup(answers.groupBy("slice")).applyInArrow(total, "doc_id long, lang string, n_bytes long, bits double")
        rounds.append(common.cut(scores, "kn-scores"))
        common.drop_cut(answers)
    common.drop_cut(slices, held)
    scored = functools.reduce(DataFrame.unionAll, rounds)
    return scored.select("doc_id", "lang", "n_bytes", F.pow(F.lit(2.0), F.col("bits") / (F.col("n_bytes") + 1)).alias("perplexity"))


def trusted_texts(docs: DataFrame, trusted: DataFrame) -> DataFrame:
    """Texts whose doc_id is in ``trusted``: a fixed-size filter first, then the exact join."""
    bits = docs.sparkSession.sparkContext.broadcast(common.key_filter(trusted, "doc_id"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").fill_null(-1).to_numpy(zero_copy_only=False)
            yield batch.filter(pa.array(common.in_filter(bits.value, ids)))

    some = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, text string")
    # the list of trusted documents grows with the corpus, so it is never the broadcast side
    return some.join(trusted.hint("merge"), "doc_id", "left_semi")


def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", tokenizer: str | None = None) -> DataFrame:
    """Per document: doc_id, lang, n_bytes, perplexity, threshold, kept."""
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(lang).cast("string").alias("lang"), F.col(text).alias("text"))
    trusted = common.cut(labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id")).distinct(), "kn-trusted")
    tokenizer = tokenizer or common.tokenizer_file()
    texts = trusted_texts(src, trusted).select(fold_of(F.col("doc_id")).alias("fold"), "text")
    made: list[DataFrame] = []
    tables = lookup_tables(fit_tokens(texts, tokenizer, made), tokenizer)
    common.drop_cut(*made)
    scores = perplexities(src, tables, tokenizer)
    good = scores.join(trusted, "doc_id", "left_semi").where("perplexity is not null")
    at = F.percentile_approx("perplexity", quantile, 10_000)
    limits = good.groupBy("lang").agg(at.alias("own"))
    every = good.agg(at.alias("every"))
    out = scores.join(limits.withColumnRenamed("lang", "l"), F.col("lang").eqNullSafe(F.col("l")), "left").join(F.broadcast(every))
    limit = F.coalesce("own", "every", F.lit(float("inf")))
    return out.select("doc_id", "lang", "n_bytes", "perplexity", limit.alias("threshold"), F.coalesce(F.col("perplexity") <= limit, F.lit(False)).alias("kept"))
