"""Secret scan with linking of multipart credentials, in DataFrame functions only.

Base patterns report strong secrets.  Beside them, weak parts are looked for: account
identifiers, opaque tokens and endpoints, each too common to report alone.  An interval join in
the form of running extremes over the parts of one document, in order of position, gives each
weak part the nearest complementary part before and after it; it is reported only if that lies
within the scope (``SCOPE`` code points):

- ``wsecret`` (opaque token): an identifier or an endpoint in scope;
- ``wid`` (account identifier): a secret, strong or weak, in scope;
- ``endpoint``: an identifier and a secret in scope.

A strong span inside the value of an identifier does not confirm that one; inside an endpoint it is a secret in scope.
Neither keeps the weak part from being one.  An opaque token is left out only where a strong span covers it whole.

Only positions are shuffled, and only of documents with at least one weak part.

Defined cases: a null text is empty (no spans); repeated rows give equal results; null doc_id
is a value like others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

SCOPE = 256

# Kind, pattern, group that is measured, least length of that group.
BASE_KINDS = (
    ("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12),
    ("access", r"AKIA[A-Z0-9]{14,}", 0, 18),
    ("hex", r"[0-9a-f]{16,}", 0, 16),
)
WEAK_KINDS = (
    ("wid", r"""(?i:\b(?:access|client|account|user|app|aws)[_-]?(?:access[_-]?)?(?:key[_-]?)?(?:id|name))["']?\x20*[:=]\x20*["']?[A-Za-z0-9._@-]{4,}""", 0, 8),
    ("wsecret", r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_-]*+[0-9])(?=[A-Z0-9+/_-]*+[a-z])(?=[a-z0-9+/_-]*+[A-Z])[A-Za-z0-9+/_-]{24,}={0,2}", 0, 24),
    ("endpoint", r"""\b(?:https?|wss?|ftp|sftp|ssh|amqp|redis|mongodb|postgres|mysql|jdbc:[a-z]+)://[^\s"'<>]+""", 0, 8),
)
KINDS = [k for k, *_ in (*BASE_KINDS, *WEAK_KINDS)]

SPANS = "array<struct<kind:int,start:int,end:int>>"


def spans(text: Column, kind: int, pattern: str, group: int, least: int) -> Column:
    """Spans (code points, end exclusive) of the leftmost non-overlapping matches whose
    group has ``least`` code points at least; the texts between matches give the positions."""
    pat = F.lit(pattern)
    hit = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, pat, F.lit(0)).alias("all"), F.regexp_extract_all(text, pat, F.lit(group)).alias("part"))

    def step(acc: Column, x: Column) -> Column:
        start = (acc["at"] + F.length(x["gap"])).cast("int")
        end = (start + F.coalesce(F.length(x["all"]), F.lit(0))).cast("int")
        one = F.struct(F.lit(kind).cast("int").alias("kind"), start.alias("start"), end.alias("end"))
        return F.struct(end.alias("at"), F.when(F.length(x["part"]) >= least, F.concat(acc["out"], F.array(one))).otherwise(acc["out"]).alias("out"))

    none = F.array().cast(SPANS)
    found = F.aggregate(hit, F.struct(F.lit(0).cast("int").alias("at"), none.alias("out")), step, lambda acc: acc["out"])
    return F.when(text.rlike(pattern), found).otherwise(none)


def parts_of(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Base spans and weak parts of each document, positions only."""
    body = F.coalesce(F.col(text), F.lit(""))
    src = docs.select(F.col(doc_id).cast("long").alias("doc_id"), body.alias("body"))
    base = [spans(F.col("body"), k, *rule[1:]).alias(rule[0]) for k, rule in enumerate(BASE_KINDS)]
    weak = [spans(F.col("body"), k + len(BASE_KINDS), *rule[1:]).alias(rule[0]) for k, rule in enumerate(WEAK_KINDS)]
    row = src.select("doc_id", F.xxhash64("doc_id", "body").alias("key"), *base, *weak)
    return row.select("doc_id", "key", F.concat(*[r[0] for r in BASE_KINDS]).alias("base"), F.concat(*[r[0] for r in WEAK_KINDS]).alias("weak"))


def link(parts: DataFrame, scope: int = SCOPE) -> DataFrame:
    """(key, extra): the weak parts of each document that complementary parts confirm."""
    some = parts.where(F.size("weak") > 0).select("key", F.concat("base", "weak").alias("all")).dropDuplicates(["key"])
    one = some.select("key", F.inline("all"))
    base, wid, wsecret, endpoint = F.col("kind") < len(BASE_KINDS), *(F.col("kind") == k for k in (3, 4, 5))
    by_start = Window.partitionBy("key").orderBy("start")
    upto, onward = by_start.rangeBetween(Window.unboundedPreceding, 0), by_start.rangeBetween(0, Window.unboundedFollowing)

    def covered(role: Column) -> Column:
        return F.coalesce(F.max(F.when(role, F.col("end"))).over(upto) >= F.col("end"), F.lit(False))

    def covers(role: Column) -> Column:
        return F.coalesce(F.min(F.when(role, F.col("end"))).over(onward) <= F.col("end"), F.lit(False))

    # a weak token that a strong span covers is that secret itself, not another part
    seen = one.select("*", covered(base).alias("in_base"), covered(wid).alias("in_wid"), covered(endpoint).alias("in_end")).where(~(wsecret & F.col("in_base")))
    # a strong span in the value of an identifier is no other part for that one; for all others it stands where its cover does
    seen = seen.withColumn("holds", (wid & covers(base)) | (endpoint & covers(base & ~F.col("in_wid"))))
    secret = wsecret | (base & ~F.col("in_wid") & ~F.col("in_end")) | F.col("holds")
    near = Window.partitionBy("key").orderBy("start", "end", "kind")
    back, fore = near.rowsBetween(Window.unboundedPreceding, -1), near.rowsBetween(1, Window.unboundedFollowing)

    def close(role: Column) -> Column:
        before = F.max(F.when(role, F.col("end"))).over(back)
        after = F.min(F.when(role, F.col("start"))).over(fore)
        return F.coalesce(F.col("start") - before <= scope, F.lit(False)) | F.coalesce(after - F.col("end") <= scope, F.lit(False))

    # an access key id is an account identifier as well
    judged = seen.select("key", "kind", "start", "end", close(wid | (F.col("kind") == 1)).alias("near_id"), close(secret).alias("near_secret"), close(endpoint).alias("near_end"), "holds")
    good = judged.where((wid & F.col("near_secret")) | (wsecret & (F.col("near_id") | F.col("near_end"))) | (endpoint & F.col("near_id") & (F.col("near_secret") | F.col("holds"))))
    return good.groupBy("key").agg(F.collect_list(F.struct("kind", "start", "end")).alias("extra"))


def scan(docs: DataFrame, scope: int = SCOPE, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: doc_id, key, base and all spans (arrays of kind, start, end in order)."""
    parts = common.cut(parts_of(docs, doc_id, text), "secret-parts")
    joined = parts.join(link(parts, scope), "key", "left")
    in_order = lambda xs: F.transform(F.array_sort(F.transform(xs, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end")))), lambda x: x)
    extra = F.coalesce("extra", F.array().cast(SPANS))
    return joined.select("doc_id", "key", in_order(F.col("base")).alias("base"), in_order(F.concat("base", extra)).alias("spans"))


def as_text(spans_col: str) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(F.col(spans_col), lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")


def count_kind(spans_col: str, kind: int) -> Column:
    return F.size(F.filter(F.col(spans_col), lambda x: x["kind"] == kind)).cast("long")


def redact(docs: DataFrame, mark: str = "[SECRET]", scope: int = SCOPE, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with every reported span (overlapping spans as one) replaced by ``mark``; all
    columns stay.  Null texts stay null."""
    found = scan(docs, scope, doc_id, text).where(F.size("spans") > 0).select(F.col("key").alias("k"), F.col("spans").alias("s")).dropDuplicates(["k"])
    body = F.coalesce(F.col(text), F.lit(""))
    keyed = docs.select(F.struct(*docs.columns).alias("row"), F.xxhash64(F.col(doc_id).cast("long"), body).alias("k"))
    row = keyed.join(found, "k", "left")

    def step(acc, x):
        cut = F.greatest(x["start"], acc["at"])
        fresh = x["start"] >= acc["at"]
        lead = F.col("row")[text].substr(acc["at"] + 1, cut - acc["at"])
        return F.struct(F.greatest(x["end"], acc["at"]).alias("at"), F.when(fresh, F.concat(acc["out"], lead, F.lit(mark))).otherwise(acc["out"]).alias("out"))

    start = F.struct(F.lit(0).cast("int").alias("at"), F.lit("").alias("out"))
    clean = F.aggregate("s", start, step, lambda acc: F.concat(acc["out"], F.col("row")[text].substr(acc["at"] + 1, F.length(F.col("row")[text]))))
    new = F.when(F.col("s").isNull(), F.col("row")[text]).otherwise(clean)
    return row.select(*[(new if c == text else F.col("row")[c]).alias(c) for c in docs.columns])
