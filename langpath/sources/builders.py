"""Graphs of the experiments, built from the given tables.

Vertices of several tables share one space of ids: ``key * 16 + kind``, plain arithmetic that any engine
can repeat."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import LabeledGraph
from .io import load

KINDS = {"region": 0, "nation": 1, "customer": 2, "supplier": 3, "part": 4, "order": 5, "brand": 6, "size": 7, "event": 8, "user": 9, "turn": 10, "page": 11, "href": 12}
BRANDS, SIZES = 25, 50


def vid(key: Column | str, kind: str) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return key.cast("long") * 16 + KINDS[kind]


def _edge(src: Column, label: str, dst: Column) -> list[Column]:
    return [src.alias("src"), F.lit(label).alias("label"), dst.alias("dst")]


def _union(*frames: DataFrame) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def trail(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Each event to the user's next, labelled by the earlier event's type; a second edge ``flagged``
    where its ``$.k`` is below 20.  A piece is a user."""
    ev = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "props")
    nxt = F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    row = ev.select("event_id", "event_type", nxt.alias("nxt"), F.get_json_object("props", "$.k").cast("int").alias("k")).where("nxt is not null")
    labels = F.when(F.col("k") < 20, F.array("event_type", F.lit("flagged"))).otherwise(F.array("event_type"))
    edges = row.select(F.col("event_id").cast("long").alias("src"), F.explode(labels).alias("label"), F.col("nxt").cast("long").alias("dst"))
    vertices = ev.select(F.col("event_id").cast("long").alias("id"))
    pieces = ev.select(F.col("event_id").cast("long").alias("id"), F.col("user_id").cast("long").alias("piece"))
    return LabeledGraph(edges, vertices, pieces)


def handoff(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """User of an event to the user of the next event over the whole table."""
    ev = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    # the next event over all users: within time slices first, then across their borders, so that
    # no task gets the whole table
    slot = ev.withColumn("slot", F.date_trunc("hour", "ts"))
    w = Window.partitionBy("slot").orderBy("ts", "event_id")
    row = slot.select("slot", "user_id", "event_type", F.lead("user_id").over(w).alias("nxt"), F.row_number().over(w).alias("k"))
    head = row.where("k = 1").select(F.col("slot").alias("s"), F.col("user_id").alias("first_user"))
    slots = head.select("s", F.lag("s").over(Window.orderBy("s")).alias("before"), "first_user").where("before is not null")
    inner = row.where("nxt is not null").select("user_id", "event_type", "nxt")
    border = row.where("nxt is null").join(F.broadcast(slots), F.col("slot") == F.col("before")).select("user_id", "event_type", F.col("first_user").alias("nxt"))
    e = inner.union(border).select(F.col("user_id").cast("long").alias("src"), F.col("event_type").alias("label"), F.col("nxt").cast("long").alias("dst"))
    return LabeledGraph(e.distinct(), ev.select(F.col("user_id").cast("long").alias("id")).distinct())


def _lattice(spark: SparkSession, kind: str, top: int) -> DataFrame:
    n = spark.range(1, top + 1)
    return _union(*(n.select(*_edge(vid("id", kind), "sco", vid(F.floor(F.col("id") / d), kind))) for d in (2, 3))).distinct()


def ontology(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Things with their classes (``type``) and a lattice of classes (``sco``), with inverses."""
    part, cust, supp, nation = (load(spark, sf_dir, t) for t in ("part", "customer", "supplier", "nation"))
    brand = F.regexp_extract("p_brand", r"(\d+)$", 1).cast("long")
    e = _union(
        part.select(*_edge(vid("p_partkey", "part"), "type", vid(brand, "brand"))),
        part.select(*_edge(vid("p_partkey", "part"), "type", vid("p_size", "size"))),
        cust.select(*_edge(vid("c_custkey", "customer"), "type", vid("c_nationkey", "nation"))),
        supp.select(*_edge(vid("s_suppkey", "supplier"), "type", vid("s_nationkey", "nation"))),
        nation.select(*_edge(vid("n_nationkey", "nation"), "sco", vid("n_regionkey", "region"))),
        _lattice(spark, "brand", BRANDS),
        _lattice(spark, "size", SIZES),
    )
    return LabeledGraph.of(e).with_inverses()


def territory(spark: SparkSession, sf_dir: str, full: bool = False) -> LabeledGraph:
    """Supplier (and customer) to nation to region by ``bt``, with inverses."""
    supp, nation = load(spark, sf_dir, "supplier"), load(spark, sf_dir, "nation")
    e = _union(supp.select(*_edge(vid("s_suppkey", "supplier"), "bt", vid("s_nationkey", "nation"))), nation.select(*_edge(vid("n_nationkey", "nation"), "bt", vid("n_regionkey", "region"))))
    if full:
        e = e.unionByName(load(spark, sf_dir, "customer").select(*_edge(vid("c_custkey", "customer"), "bt", vid("c_nationkey", "nation"))))
    return LabeledGraph.of(e).with_inverses()


def pointer(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """``d``: urgent order to customer to nation to region; ``a``: urgent order to the next of the same day."""
    o = load(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_custkey", "o_orderdate")
    cust, nation, region = (load(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    nxt = F.lead("o_orderkey").over(Window.partitionBy("o_orderdate").orderBy("o_orderkey"))
    e = _union(
        o.select(*_edge(vid("o_orderkey", "order"), "d", vid("o_custkey", "customer"))),
        cust.select(*_edge(vid("c_custkey", "customer"), "d", vid("c_nationkey", "nation"))),
        nation.select(*_edge(vid("n_nationkey", "nation"), "d", vid("n_regionkey", "region"))),
        o.withColumn("nxt", nxt).where("nxt is not null").select(*_edge(vid("o_orderkey", "order"), "a", vid("nxt", "order"))),
    )
    v = _union(
        o.select(vid("o_orderkey", "order").alias("id")), cust.select(vid("c_custkey", "customer").alias("id")),
        nation.select(vid("n_nationkey", "nation").alias("id")), region.select(vid("r_regionkey", "region").alias("id")),
    )
    return LabeledGraph.of(e, v.distinct()).with_inverses()


def dialogue(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Turn to next turn of a conversation, labelled by the earlier turn's role.  A piece is a conversation."""
    c = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    nxt = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    me = lambda t: (F.col("conv_id") * 16 + F.col(t)).cast("long")
    e = c.withColumn("nxt", nxt).where("nxt is not null").select(me("turn").alias("src"), F.col("role").alias("label"), me("nxt").alias("dst"))
    return LabeledGraph(e.distinct(), c.select(me("turn").alias("id")).distinct(), c.select(me("turn").alias("id"), F.col("conv_id").cast("long").alias("piece")).distinct())


def weblinks(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Page to link target, by ``links``, with inverses; targets are named by a hash."""
    p = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("href"))
    target = F.shiftleft(F.shiftrightunsigned(F.xxhash64("href"), 5), 4) + KINDS["href"]
    return LabeledGraph.of(p.select(*_edge(vid("page_id", "page"), "links", target))).with_inverses()


def commerce(spark: SparkSession, sf_dir: str, inverses: list[str] | None = None) -> LabeledGraph:
    """Orders, parts, suppliers, customers, nations and regions."""
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    cust, supp, nation = (load(spark, sf_dir, t) for t in ("customer", "supplier", "nation"))
    order, part, sup = vid("l_orderkey", "order"), vid("l_partkey", "part"), vid("l_suppkey", "supplier")
    # one scan of the large table gives three kinds of edges
    three = li.select(F.inline(F.array(F.struct(*_edge(order, "contains", part)), F.struct(*_edge(order, "shipped_by", sup)), F.struct(*_edge(part, "sold_by", sup)))))
    e = _union(
        three,
        o.select(*_edge(vid("o_orderkey", "order"), "placed_by", vid("o_custkey", "customer"))),
        cust.select(*_edge(vid("c_custkey", "customer"), "located", vid("c_nationkey", "nation"))),
        supp.select(*_edge(vid("s_suppkey", "supplier"), "located", vid("s_nationkey", "nation"))),
        nation.select(*_edge(vid("n_nationkey", "nation"), "within", vid("n_regionkey", "region"))),
    )
    g = LabeledGraph.of(e)
    return g.with_inverses(inverses) if inverses else g


def range_edges(spark: SparkSession, sf_dir: str, hours: int = 2) -> DataFrame:
    """Event to each later event of the same user within some hours (interval join on buckets of time)."""
    ev = load(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    sec = hours * 3600
    a = ev.select(F.col("event_id").alias("src"), F.col("ts").alias("t0"), "user_id", F.floor(F.unix_timestamp("ts") / sec).alias("b"))
    b = a.select(F.col("src").alias("dst"), F.col("t0").alias("t1"), "user_id", F.explode(F.array("b", F.col("b") - 1)).alias("b"))
    hit = a.join(b, ["user_id", "b"]).where(f"t1 > t0 and t1 <= t0 + interval {hours} hours")
    return hit.select(F.col("src").cast("long"), F.lit("soon").alias("label"), F.col("dst").cast("long"))


def asof_edges(spark: SparkSession, sf_dir: str, date: str) -> DataFrame:
    """Customer to its latest order before a date (snapshot of a graph in time)."""
    o = load(spark, sf_dir, "orders").where(F.col("o_orderdate") < F.lit(date).cast("timestamp"))
    last = o.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("k"))
    return last.select(vid("o_custkey", "customer").alias("src"), F.lit("latest").alias("label"), vid("k", "order").alias("dst"))


BUILDERS = {"trail": trail, "handoff": handoff, "ontology": ontology, "territory": territory, "territory_full": lambda s, d: territory(s, d, full=True), "pointer": pointer, "dialogue": dialogue, "weblinks": weblinks, "commerce": commerce}
