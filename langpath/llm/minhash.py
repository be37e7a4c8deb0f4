"""Near-duplicate links by MinHash with tensored banding.

Two small collections of ``TABLES`` keys each are computed per document, a key being ``WIDTH``
minhashes.  A table key pairs one key of either collection, so ``TABLES``**2 tables of
``2 * WIDTH`` minhashes come from ``2 * TABLES * WIDTH`` minhash functions instead of
``2 * WIDTH * TABLES**2``.  Two sets of similarity s meet in no table with a probability below
``2 * (1 - s**WIDTH)**TABLES``: 7e-5 at s = 0.8, 5e-8 at 0.9.

Before pairing, keys that only one document has are dropped: no table key made from them can be
shared.  Documents of one shingle set are one class from the start.  Buckets are then linked
without listing pairs of what is already linked:

1. each class is checked against the smallest class of its buckets;
2. in buckets with several components left, each class outside the bucket's largest component is
   checked against a pseudo-random member, another one in each bucket; a quarter of the buckets at a time, and of each
   class and component one pair that the bounds below allow;
3. what then still lies outside its bucket's largest component is checked against all classes it shares a table with in other
   components.  Here a table is met by its factors: both classes have one key of either collection in common, so a class
   needs ``TABLES`` rows and not the square.  One pair of each class and other component goes first; what that links needs
   no further check.

Pairs are checked on full shingle sets only if two exact bounds allow the similarity: the sizes
of the sets, and the parity sketch.  The sketch has one bit per bin of hashes, the parity of the set's
members in it; two sketches differ in at most as many bits as the sets have unshared members, and
similarity s needs at most (1 - s) / (1 + s) of both sizes of these.

Every pair of classes that share a bucket ends up in one component or has been ruled out by a bound or by
full shingle sets; so no link between different texts of a bucket is lost, and a group of n near
copies costs about n checks, not n**2.

Defined cases: null or wordless texts have an empty set and link with nothing, not even with each
other; a text with fewer words than a shingle is one shingle; rows repeated with one doc_id share its class; null doc_id
is left out when the smallest is taken (a component of nulls only has a null id); an empty table gives
no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common
from .components import components

TABLES, WIDTH = 14, 3
SHINGLE_WORDS, PERCENT = 2, 80
SKETCH = 16  # 64-bit words of the parity sketch


def shingle_sets(column: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes, start, class) of the distinct shingles of texts; class names the set, -1 if it is empty."""
    raw, off = common.flat_text(column)
    _, _, h, first = common.words_of(raw, off, lower=True)
    h, start = common.distinct(*common.shingles(h, first, width))
    n = np.diff(start)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(common.mix(h))])
    cls = common.mix((total[start[1:]] - total[start[:-1]]) * np.uint64(0x9E3779B97F4A7C15) + n.astype(np.uint64)).view(np.int64)
    return h, start, np.where(n > 0, cls & np.int64((1 << 63) - 1), -1)


def band_keys(h: np.ndarray, start: np.ndarray, tables: int = TABLES, width: int = WIDTH) -> np.ndarray:
    """Keys of both collections, (sets, 2 * tables); all sets must have a shingle."""
    odd = common.mix(np.arange(1, 2 * tables * width + 1, dtype=np.uint64)) | np.uint64(1)
    flip = common.mix(odd)
    out = np.empty((len(start) - 1, 2 * tables), np.uint64)
    for t in range(2 * tables):
        key = np.full(len(start) - 1, np.uint64(t + 1))
        for j in range(t * width, (t + 1) * width):
            low = np.minimum.reduceat((h ^ flip[j]) * odd[j], start[:-1]) if len(h) else key
            key = common.mix(key * np.uint64(0x9E3779B97F4A7C15) + low)
        out[:, t] = key
    return out.view(np.int64)


def sketches(h: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Parity sketch of each set, (sets, SKETCH) int64."""
    bins = SKETCH * 64
    owner = np.repeat(np.arange(len(start) - 1, dtype=np.int64), np.diff(start))
    at = owner * bins + (common.mix(h + np.uint64(7)) % np.uint64(bins)).astype(np.int64)
    odd = np.bincount(at, minlength=(len(start) - 1) * bins) & 1
    return np.packbits(odd.astype(bool)).view(np.int64).reshape(-1, SKETCH)


def features(docs: DataFrame, words: int, doc_id: str, text: str) -> DataFrame:
    """doc_id, n_shingles, class, the keys of both collections and the sketch."""
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "text"):
            h, start, cls = shingle_sets(batch.column("text"), words)
            n = np.diff(start)
            full = np.flatnonzero(n)
            own = np.concatenate([start[full], start[-1:]])
            keys, sketch = band_keys(h, own), sketches(h, own)
            width = np.where(n > 0, SKETCH, 0)
            drawn = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(width)]).astype(np.int32)), pa.array(sketch.reshape(-1)))
            size = np.where(n > 0, 2 * TABLES, 0)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.array(keys.reshape(-1)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n), pa.array(cls), lists, drawn], ["doc_id", "n_shingles", "class", "keys", "sketch"])

    return src.mapInArrow(run, "doc_id long, n_shingles long, class long, keys array<long>, sketch array<long>")


def sets_of(docs: DataFrame, wanted: DataFrame, words: int, doc_id: str, text: str) -> DataFrame:
    """(class, shingles) of the wanted classes, from one document of each."""
    bits = docs.sparkSession.sparkContext.broadcast(common.key_filter(wanted, "class"))
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.slices(batches, "text"):
            h, start, cls = shingle_sets(batch.column("text"), words)
            some = np.flatnonzero(common.in_filter(bits.value, cls) & (cls >= 0))
            n = np.diff(start)[some]
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32)), pa.array(h[common.gather(start[some], n)].view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(some)), pa.array(cls[some]), lists], ["doc_id", "class", "shingles"])

    found = src.mapInArrow(run, "doc_id long, class long, shingles array<long>")
    one = found.join(wanted.select("class", F.col("who").alias("w")), [found["class"] == wanted["class"], found["doc_id"].eqNullSafe(F.col("w"))]).select(found["class"], "shingles")
    return one.dropDuplicates(["class"])


def _buckets(classes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(key, class, lead) of all tables in which a class is not alone, of buckets with the same members one; and the
    shared keys (class, a, b) that table keys are made from."""
    tagged = classes.select("class", F.posexplode("keys").alias("t", "k"))
    shared = tagged.groupBy("k").agg(F.count("*").alias("c")).where("c > 1").select("k")
    alive = tagged.join(shared, "k").groupBy("class").agg(
        F.collect_list(F.when(F.col("t") < TABLES, F.col("k"))).alias("a"), F.collect_list(F.when(F.col("t") >= TABLES, F.col("k"))).alias("b")
    )
    alive = common.cut(alive.where((F.size("a") > 0) & (F.size("b") > 0)), "mh-alive")
    pair = F.flatten(F.transform("a", lambda x: F.transform("b", lambda y: F.xxhash64(x, y))))
    rows = common.cut(alive.select("class", F.explode(pair).alias("key")), "mh-keys")
    full = rows.groupBy("key").agg(F.count("*").alias("c"), F.sum(F.xxhash64("class").cast("decimal(38,0)")).alias("who"), F.min("class").alias("lead")).where("c > 1")
    chosen = full.groupBy("c", "who").agg(F.min("key").alias("key"), F.first("lead").alias("lead"))
    out = common.cut(rows.join(chosen.select("key", "lead"), "key"), "mh-buckets")
    common.drop_cut(rows)
    return out, alive


def _mixed(buckets: DataFrame, label: DataFrame) -> DataFrame:
    """(key, class, root, main) of the buckets with several components, lazily; main is the largest."""
    at = buckets.select("key", "class").join(label, "class")
    sized = at.groupBy("key", "root").agg(F.count("*").alias("c"))
    main = sized.groupBy("key").agg(F.count("*").alias("roots"), F.max_by("root", F.struct("c", "root")).alias("main")).where("roots > 1").select("key", "main")
    return at.join(main, "key")


def _one_each(pairs: DataFrame) -> DataFrame:
    """One pair of each class and other component."""
    return pairs.groupBy("x", "ry").agg(F.min_by("y", F.xxhash64("x", "y")).alias("y"))


def _advance(pairs: DataFrame, label: DataFrame, tested: DataFrame, sets: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """Check the pairs not tested before: components after it, and all tested pairs."""
    fresh = common.cut(_ordered(pairs).join(tested, ["x", "y"], "left_anti"), "mh-tested")
    links = common.cut(_checked(fresh, sets, percent), "mh-links")
    new = _relabel(label, links)
    both = common.cut(tested.union(fresh), "mh-tested")
    common.drop_cut(fresh, links, label, tested)
    return new, both


def _described(members: DataFrame, end: str) -> DataFrame:
    """(end, size, sketch words) of the member classes, named for one end of a pair."""
    words = [F.col("sketch")[k].alias(f"{end}{k}") for k in range(SKETCH)]
    return members.select(F.col("class").alias(end), F.col("n").alias(f"n{end}"), *words)


def _possible(percent: int) -> Column:
    """Whether sizes and sketches of x and y allow the similarity; both bounds are exact."""
    small, large = F.least("nx", "ny"), F.greatest("nx", "ny")
    apart = reduce(lambda a, b: a + b, [F.bit_count(F.col(f"x{k}").bitwiseXOR(F.col(f"y{k}"))) for k in range(SKETCH)])
    return (F.col("x") != F.col("y")) & (small * 100 >= large * percent) & (apart * (100 + percent) <= (small + large) * (100 - percent))


def _checked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (x, y) whose full sets are similar enough."""
    left = pairs.select("x", "y").join(sets.select(F.col("class").alias("x"), F.col("shingles").alias("sx")), "x")
    both = left.join(sets.select(F.col("class").alias("y"), F.col("shingles").alias("sy")), "y")
    inter = F.size(F.array_intersect("sx", "sy"))
    return both.select("x", "y", inter.alias("i"), (F.size("sx") + F.size("sy")).alias("s")).where(F.col("i") * 100 >= (F.col("s") - F.col("i")) * percent).select("x", "y")


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()


def _relabel(label: DataFrame, links: DataFrame) -> DataFrame:
    """Join components that links connect; label: (class, root)."""
    at = lambda c: label.select(F.col("class").alias(c), F.col("root").alias(f"r{c}"))
    meta = links.join(at("x"), "x").join(at("y"), "y").where("rx <> ry").select(F.col("rx").alias("x"), F.col("ry").alias("y"))
    merged = components(meta).select(F.col("v").alias("root"), F.col("root").alias("new"))
    return common.cut(label.join(merged, "root", "left").select("class", F.coalesce("new", "root").alias("root")), "mh-label")


def link(docs: DataFrame, words: int = SHINGLE_WORDS, percent: int = PERCENT, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles, component_id (smallest doc_id reachable)."""
    spark = docs.sparkSession
    feats = common.cut(features(docs, words, doc_id, text), "mh-features")
    classes = feats.where("n_shingles > 0").groupBy("class").agg(F.min("doc_id").alias("who"), F.min("n_shingles").alias("n"), F.first("keys").alias("keys"), F.first("sketch").alias("sketch"))
    classes = common.cut(classes, "mh-classes")
    buckets, alive = _buckets(classes)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    members = common.cut(classes.select("class", "who", "n", "sketch").join(alive, "class").join(buckets.select("class").distinct(), "class"), "mh-members")
    common.drop_cut(alive)
    sets = sets_of(docs, members, words, doc_id, text).repartition(parts, "class").persist(StorageLevel.DISK_ONLY)
    possible, x, y = _possible(percent), _described(members, "x"), _described(members, "y")

    # 1. the smallest class of its buckets
    star = buckets.where("class <> lead").groupBy(F.col("class").alias("x")).agg(F.min("lead").alias("y"))
    tested = common.cut(_ordered(star.join(x, "x").join(y, "y").where(possible)), "mh-tested")
    links = common.cut(_checked(tested, sets, percent), "mh-links")
    label = _relabel(members.select("class", F.col("class").alias("root")), links)
    common.drop_cut(links)

    # 2. pseudo-random members of the largest component of mixed buckets, a quarter of the buckets at a time
    for share in range(2):
        mixed = common.cut(_mixed(buckets.where(F.pmod(F.xxhash64("key"), F.lit(4)) == share), label), "mh-mixed")
        out = mixed.where("root <> main").select("key", F.col("class").alias("x"), F.col("root").alias("rx")).join(x, "x")
        ends = mixed.where("root = main").select("key", F.col("class").alias("y"), F.col("root").alias("ry"), "main")
        ends = ends.groupBy("key").agg(F.min_by(F.struct("y", "ry"), F.xxhash64("y", "key", "main")).alias("e")).select("key", "e.*")
        label, tested = _advance(_one_each(out.join(ends.join(y, "y"), "key").where(possible)), label, tested, sets, percent)
        common.drop_cut(mixed)

    # 3. what still lies outside: first one pair of each class and component, then all pairs
    for every in (False, True):
        opened = common.cut(_mixed(buckets, label).where("root <> main").select("class").distinct(), "mh-open")
        named = members.select("class", "a", "b").join(label, "class")
        out = named.join(opened, "class").select(F.explode("a").alias("k"), F.col("class").alias("x"), F.col("root").alias("rx"), F.col("b").alias("bx"))
        out = common.cut(out, "mh-out")
        ends = named.select(F.explode("a").alias("k"), F.col("class").alias("y"), F.col("root").alias("ry"), F.col("b").alias("by"))
        ends = ends.join(out.select("k").distinct(), "k", "left_semi")
        met = out.join(x, "x").join(ends.join(y, "y"), "k").where(possible & (F.col("rx") != F.col("ry")) & F.arrays_overlap("bx", "by"))
        label, tested = _advance(met if every else _one_each(met), label, tested, sets, percent)
        common.drop_cut(opened, out)
    sets.unpersist()
    common.drop_cut(buckets, members, tested)

    named = classes.select("class", "who").join(label, "class", "left").withColumn("root", F.coalesce("root", "class"))
    # a table of its own, so that a root with very many classes can be split when both meet
    least = common.cut(named.groupBy("root").agg(F.min("who").alias("component_id")), "mh-least")
    of_class = named.join(least, "root").select("class", "component_id")
    rows = feats.select("doc_id", "n_shingles", "class").join(of_class, "class", "left")
    return rows.select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, words: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents of smallest doc_id of each group of near copies, and all that have none.  A
    document without a doc_id is never dropped."""
    linked = link(docs, words, percent, doc_id, text)
    gone = linked.where(F.col("component_id") != F.col("doc_id")).select(F.col("doc_id").alias(doc_id)).distinct()
    return docs.join(gone, doc_id, "left_anti").select(*docs.columns)
