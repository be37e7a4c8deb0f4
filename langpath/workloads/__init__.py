"""Driver workloads: experiment queries on the given tables, each with its SQL twin where one exists."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import LabeledGraph
from ..language import fsm as fa
from ..language import grammar as gr
from ..language import rsm
from ..operators import baselines, boolmat, closure, kron, measure
from ..operators import index as ix
from ..operators import paths as pt
from ..operators import twins
from ..plans.sqlfront import LangPathSession
from ..runtime import Stage
from ..sources import builders as B
from ..sources.io import load
from ..streaming import Maintained, session_trails, trail_edges, windowed_labels
from . import sql as S
from .templates import GRAMMARS, TEMPLATES, TRAIL, bind

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}

AB = {"a": "click", "b": "purchase"}
ABC = {"a": "click", "b": "purchase", "c": "view"}


def register(name: str, run: Query, oracle: str | None = None) -> None:
    QUERIES[name] = run
    if oracle:
        ORACLE[name] = oracle


def query(oracle: str | None = None, name: str | None = None):
    def wrap(f: Query) -> Query:
        register(name or f.__name__, f, oracle)
        return f

    return wrap


def machine_of(name: str, binding: dict[str, str] | None = None, start: str | None = None) -> rsm.RecursiveMachine:
    return rsm.from_grammar(gr.parse(bind(GRAMMARS[name], binding or {}), start))


def grammar_of(name: str, binding: dict[str, str] | None = None) -> gr.Grammar:
    return gr.parse(bind(GRAMMARS[name], binding or {}))


def _regular(name: str, graph: str, text: str, strategy: str = "auto") -> None:
    register(name, lambda s, d: ix.build(B.BUILDERS[graph](s, d), fa.from_regex(text), strategy=strategy).reachable(), S.regular(graph, text))


# --------------------------------------------------------------------------- regular queries
for _k, _t in TEMPLATES.items():
    _regular(f"rpq_{_k}", "trail", bind(_t, TRAIL))
for _k in ("q1", "q2", "q5", "q11_2", "q12", "q16"):
    _regular(f"rpq_handoff_{_k}", "handoff", bind(TEMPLATES[_k], TRAIL), strategy="auto" if _k in ("q11_2", "q16") else "hubs")
_regular("rpq_onto_q2", "ontology", "type sco*")
_regular("rpq_onto_q9", "ontology", "(sco | sco~)+")
_regular("rpq_dialogue_q12", "dialogue", "(user assistant)+ | (system user)+")
_regular("rpq_dialogue_q5", "dialogue", "system user* assistant")
_regular("rpq_commerce_q11_3", "commerce", "placed_by located within")
_regular("rpq_commerce_q16", "commerce", "sold_by located (within)?")


@query("with l as (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) href from pages)\nselect distinct a.page_id * 16 + 11 src, b.page_id * 16 + 11 dst from l a join l b on a.href = b.href")
def rpq_web_cocite(spark, sf_dir):
    return ix.build(B.weblinks(spark, sf_dir), fa.from_regex("links links~")).reachable()


# --------------------------------------------------------------------------- grammar queries
def _grammar(name: str, grammar: str, graph: str, oracle: str, binding: dict[str, str] | None = None, box: str | None = None, strategy: str = "auto", twins: bool = False, large: str = "loop") -> None:
    def run(spark, sf_dir):
        m = machine_of(grammar, binding)
        return ix.build(B.BUILDERS[graph](spark, sf_dir), m, boxes=[box] if box else None, strategy=strategy, twins=twins, large=large).reachable(box)

    register(name, run, oracle)


_grammar("cf_anbn_trail", "anbn", "trail", S.linear("anbn", "trail", AB), AB)
_grammar("cf_anbn_view_click", "anbn", "trail", S.linear("anbn", "trail", {"a": "view", "b": "click"}), {"a": "view", "b": "click"})
_grammar("cf_anbn_handoff", "anbn", "handoff", S.linear("anbn", "handoff", AB), AB, strategy="bits")
_grammar("cf_g1", "g1", "ontology", S.linear("g1", "ontology"))
_grammar("cf_g2", "g2", "ontology", S.linear("g2", "ontology"))
_grammar("cf_geo", "geo", "territory", S.linear("geo", "territory"), twins=True)
_grammar("cf_geo_full", "geo", "territory_full", S.linear("geo", "territory_full"), twins=True)
_grammar("cf_ma_s", "ma", "pointer", S.alias("S"), large="jumps")
_grammar("cf_ma_v", "ma", "pointer", S.alias("V"), box="V", large="jumps")
_grammar("cf_nullable", "nullable", "trail", S.linear("nullable", "trail", AB), AB)
_grammar("cf_ambig", "ambig", "trail", S.regular("trail", "click+"), AB)
_grammar("cf_regular_part", "regular_part", "trail", S.linear("regular_part", "trail", ABC), ABC)
for _g, _graph in (("g1", "ontology"), ("g2", "ontology"), ("geo", "territory")):
    _grammar(f"loop_{_g}", _g, _graph, S.linear(_g, _graph), strategy="loop", twins=_g == "geo")

# --------------------------------------------------------------------------- closure variants
_VARIANTS = {"naive": ("linear", False), "scratch": ("squaring", True), "delta": ("incremental", True), "packed": ("packed", True), "table": ("table", True)}
_Q14 = bind(TEMPLATES["q14"], TRAIL)
for _v, (_c, _d) in _VARIANTS.items():
    register(f"variant_{_v}_g1", lambda s, d, c=_c, dl=_d: ix.build_full(B.ontology(s, d), machine_of("g1"), c, dl).reachable(), S.linear("g1", "ontology"))
    register(f"variant_{_v}_q14", lambda s, d, c=_c, dl=_d: ix.build_full(B.trail(s, d), fa.from_regex(_Q14), c, dl).reachable(), S.regular("trail", _Q14))
register("variant_rooted_q14", lambda s, d: ix.build(B.trail(s, d), fa.from_regex(_Q14), strategy="loop").reachable(), S.regular("trail", _Q14))
register("variant_unminimized_g1", lambda s, d: ix.build(B.ontology(s, d), rsm.from_grammar(gr.parse(GRAMMARS["g1"]), minimize=False), strategy="task").reachable(), S.linear("g1", "ontology"))


# --------------------------------------------------------------------------- baselines
def _matrix(name: str, grammar: str, graph: str, oracle: str, binding=None, delta: bool = True, twins: bool = False, blocks: set[str] | None = None) -> None:
    register(name, lambda s, d: baselines.matrix_reach(B.BUILDERS[graph](s, d), grammar_of(grammar, binding), delta, twins, blocks).where("label = 'S'").select("src", "dst"), oracle)


_matrix("matrix_g1", "g1", "ontology", S.linear("g1", "ontology"))
_matrix("matrix_g2", "g2", "ontology", S.linear("g2", "ontology"))
_matrix("matrix_naive_g2", "g2", "ontology", S.linear("g2", "ontology"), delta=False)
_matrix("matrix_geo", "geo", "territory", S.linear("geo", "territory"), twins=True)
_matrix("matrix_anbn", "anbn", "trail", S.linear("anbn", "trail", AB), AB)
_matrix("matrix_ma", "ma", "pointer", S.alias("S"), blocks={"S"})
_matrix("matrix_nullable", "nullable", "trail", S.linear("nullable", "trail", AB), AB)


def _lengths(graph: str, base: str, pairs: list[tuple[str, str]], limit: int = 64) -> str:
    values = ", ".join(f"('{x}', '{y}')" for x, y in pairs)
    return S._with(
        graph, f"w(x, y) as (values {values})",
        f"s(src, dst, len) as ({base} union select a.src, b.dst, s.len + 2 from s join g a on a.dst = s.src join g b on b.src = s.dst join w on w.x = a.label and w.y = b.label where s.len < {limit})",
        then="select src, dst, min(len) len from s group by src, dst",
    )


def _two_len(x: str, y: str) -> str:
    return f"select a.src, b.dst, 2 len from g a join g b on b.src = a.dst where a.label = '{x}' and b.label = '{y}'"


_G1_LEN = _lengths("ontology", _two_len("sco~", "sco") + " union " + _two_len("type~", "type"), [("sco~", "sco"), ("type~", "type")])
_ANBN_LEN = _lengths("trail", _two_len("click", "purchase"), [("click", "purchase")])


@query(_G1_LEN)
def matrix_single_len_g1(spark, sf_dir):
    return baselines.matrix_single_path(B.ontology(spark, sf_dir), grammar_of("g1")).where("label = 'S'").select("src", "dst", "len")


@query(_ANBN_LEN)
def matrix_single_len_anbn(spark, sf_dir):
    return baselines.matrix_single_path(B.trail(spark, sf_dir), grammar_of("anbn", AB)).where("label = 'S'").select("src", "dst", "len")


for _k in ("q2", "q5", "q12"):
    register(f"bfs_{_k}", lambda s, d, t=bind(TEMPLATES[_k], TRAIL): baselines.bfs(B.handoff(s, d), fa.from_regex(t), by_hubs=True), S.regular("handoff", bind(TEMPLATES[_k], TRAIL)))

# --------------------------------------------------------------------------- sources, targets, insertion
_Q5 = bind(TEMPLATES["q5"], TRAIL)


@query(S.regular("trail", _Q5, "select id from vs where id % 97 = 0"))
def ms_q5_src(spark, sf_dir):
    g = B.trail(spark, sf_dir)
    return ix.build(g, fa.from_regex(_Q5), sources=g.vertices.where("id % 97 = 0")).reachable()


@query(S.linear("g1", "ontology", then="select distinct src, dst from s where src % 16 = 6"))
def ms_g1_src(spark, sf_dir):
    g = B.ontology(spark, sf_dir)
    return ix.build(g, machine_of("g1"), sources=g.vertices.where("id % 16 = 6"), strategy="loop").reachable()


@query(S.regular("handoff", _Q5) + " and dst % 10 = 0")
def ms_q5_dst(spark, sf_dir):
    from ..plans.optimizer import PathPlan, execute, optimize

    g = B.handoff(spark, sf_dir)
    return execute(optimize(PathPlan(g, rsm.from_regex(_Q5), targets=g.vertices.where("id % 10 = 0"), strategy="hubs")))


@query(S.linear("g2", "ontology"))
def insert_g2(spark, sf_dir):
    g = B.ontology(spark, sf_dir)
    early = LabeledGraph(g.edges.where("(src + dst) % 32 < 16"), g.vertices)
    return ix.build(early, machine_of("g2"), strategy="loop").insert(g.edges.where("(src + dst) % 32 >= 16")).reachable()


# --------------------------------------------------------------------------- paths
@query(S.bounded_wrapped("trail", [("click", "purchase")], [("click", "purchase")], 20))
def paths_anbn_trail_20(spark, sf_dir):
    return pt.as_words(pt.all_pairs(ix.PathIndex(B.trail(spark, sf_dir), machine_of("anbn", AB), None), 20))


@query(S.bounded_words("trail", _Q5, 12))
def paths_q5_trail(spark, sf_dir):
    return pt.as_words(pt.all_pairs(ix.PathIndex(B.trail(spark, sf_dir), rsm.from_regex(_Q5), None), 12))


_Q2 = bind(TEMPLATES["q2"], TRAIL)


@query(S.bounded_words("handoff", _Q2, 2))
def paths_q2_handoff(spark, sf_dir):
    index = ix.PathIndex(B.handoff(spark, sf_dir), rsm.from_regex(_Q2), None)  # walks without calls need no facts of all pairs
    return pt.as_words(pt.union_all(list(pt.levels(index, 2, prune=False))))


_G1_ENDS = [("sco~", "sco"), ("type~", "type")]


@query(S.bounded_wrapped("ontology", _G1_ENDS, _G1_ENDS, 4))
def paths_g1_len4(spark, sf_dir):
    return pt.as_words(pt.union_all(list(pt.levels(ix.build(B.ontology(spark, sf_dir), machine_of("g1")), 4))))


@query(S.bounded_wrapped("ontology", _G1_ENDS, _G1_ENDS, 20, then="select src, dst, cast(count(*) as bigint) n from s group by src, dst"))
def paths_g1_per_pair(spark, sf_dir):
    return pt.count_pairs(ix.build(B.ontology(spark, sf_dir), machine_of("g1")), 20)


_TOPK = "select src, dst, len, word from (select src, dst, len, word, row_number() over (partition by src, dst order by len, word, way) k from r where q in (@finals)) x where k <= 3"


@query(S.bounded_words("handoff", _Q2, 2, _TOPK))
def paths_topk(spark, sf_dir):
    index = ix.PathIndex(B.handoff(spark, sf_dir), rsm.from_regex(_Q2), None)  # walks without calls need no facts of all pairs
    return pt.as_words(pt.top_k(pt.union_all(list(pt.levels(index, 2, prune=False))), 3))


@query(_ANBN_LEN)
def paths_single_len(spark, sf_dir):
    index = ix.build(B.trail(spark, sf_dir), machine_of("anbn", AB))
    return pt.single(index, 16).select("src", "dst", "len")


_AB_PLUS = "(click | view)+"


@query(S.bounded_words("trail", _AB_PLUS, 6, "select src, dst, len, cast(count(*) as bigint) n from r where q in (@finals) group by src, dst, len"))
def paths_count_by_length(spark, sf_dir):
    index = ix.PathIndex(B.trail(spark, sf_dir), rsm.from_regex(_AB_PLUS), spark.createDataFrame([], ix.FACTS))
    return pt.count_by_length(index, 6).select("src", "dst", "len", F.col("n").cast("long").alias("n"))


@query(S.bounded_words("handoff", "click view", 2, "select src, dst, len, word from r where q in (@finals) and len(list_distinct(string_split(way, ','))) = len(string_split(way, ','))"))
def paths_simple(spark, sf_dir):
    index = ix.build(B.handoff(spark, sf_dir), fa.from_regex("click view"))
    return pt.as_words(pt.simple(pt.union_all(list(pt.levels(index, 2)))))


@query("select cast(0 as bigint) wrong")
def paths_verified(spark, sf_dir):
    g, m = B.trail(spark, sf_dir), machine_of("anbn", AB)
    return pt.verify(pt.all_pairs(ix.PathIndex(g, m, None), 20), g, m).agg(F.count("*").alias("wrong"))


# --------------------------------------------------------------------------- worked example
EXAMPLE = [(0, "a", 1), (1, "a", 0), (1, "b", 1)]


def example(spark: SparkSession) -> LabeledGraph:
    return LabeledGraph(spark.createDataFrame(EXAMPLE, "src long, label string, dst long"), spark.createDataFrame([(0,), (1,)], "id long"))


def _example_full(spark):
    return ix.build_full(example(spark), machine_of("anbn"), "incremental")


@query("select * from (values (0::bigint, 1::bigint), (1, 1)) t(src, dst)")
def example_facts(spark, sf_dir):
    return _example_full(spark).reachable()


@query("select * from (values (0::bigint, 0::bigint), (0, 1), (1, 1)) t(src, dst)")
def example_nullable(spark, sf_dir):
    return ix.build_full(example(spark), machine_of("nullable"), "incremental").reachable()


@query("select cast(6 as bigint) index_edges, cast(11 as bigint) closure_pairs")
def example_index(spark, sf_dir):
    full = _example_full(spark)
    return full.index_edges.agg(F.count("*").alias("index_edges")).crossJoin(full.closure.agg(F.count("*").alias("closure_pairs")))


@query("select * from (values (1, 4::bigint, 5::bigint, 1::bigint), (2, 1, 4, 1), (3, 1, 2, 0)) t(round, product_new, closure_new, facts_new)")
def example_trace(spark, sf_dir):
    return measure.trace(_example_full(spark).metrics, spark).select("round", "product_new", "closure_new", "facts_new")


@query("select * from (values (0::bigint, 1::bigint, true), (1, 1, true)) t(src, dst, infinite)")
def paths_infinite_anbn(spark, sf_dir):
    return pt.is_infinite(ix.build(example(spark), machine_of("anbn")))


@query("select * from (values (0::bigint, 1::bigint, true), (1, 0, false)) t(src, dst, infinite)")
def paths_infinite_regular(spark, sf_dir):
    return pt.is_infinite(ix.build(example(spark), fa.from_regex("a b*"), strategy="loop"))


@query("select * from (values (1, 'a a b b'), (2, 'a a a a b b b b'), (3, 'a a a a a a b b b b b b')) t(k, word)")
def paths_lazy(spark, sf_dir):
    walks = pt.iterate(ix.build(example(spark), machine_of("anbn")), 1, 1)
    return spark.createDataFrame([(k, " ".join(e[1] for e in next(walks))) for k in (1, 2, 3)], "k int, word string")


# --------------------------------------------------------------------------- matrix algebra
def _numbers(df: DataFrame, key: str, mod: int) -> DataFrame:
    return df.select((F.col(key) % mod).cast("long").alias("i"), (F.floor(F.col(key) / mod) % mod).cast("long").alias("j"), F.lit(1).cast("long").alias("x")).distinct()


@query("""with a as (select distinct n_nationkey % 4 i, (n_nationkey // 4) % 4 j from nation), b as (select distinct s_suppkey % 7 k, (s_suppkey // 7) % 7 l from supplier)
select cast(i * 7 + k as bigint) i, cast(j * 7 + l as bigint) j, cast(1 as bigint) x from a, b""")
def kron_matrix(spark, sf_dir):
    return kron.matrix(_numbers(load(spark, sf_dir, "nation"), "n_nationkey", 4), _numbers(load(spark, sf_dir, "supplier"), "s_suppkey", 7), 7, 7, b_is_small=True)


_TURNS = "select src, case label when 'user' then 'click' when 'assistant' then 'view' else 'error' end label, dst from (select distinct conv_id * 16 + turn src, role label, conv_id * 16 + nxt dst from (select conv_id, turn, role, lead(turn) over (partition by conv_id order by turn) nxt from conversations) t where nxt is not null) x"


def _turns(spark, sf_dir) -> LabeledGraph:
    g = B.dialogue(spark, sf_dir)
    label = F.when(F.col("label") == "user", "click").when(F.col("label") == "assistant", "view").otherwise("error")
    return LabeledGraph(g.edges.select("src", label.alias("label"), "dst"), g.vertices)


@query(S._with("handoff", f"e as ({_TURNS})", then="select g.src src1, e.src src2, g.label, g.dst dst1, e.dst dst2 from g join e on e.label = g.label"))
def kron_graphs(spark, sf_dir):
    return kron.graphs(B.handoff(spark, sf_dir), _turns(spark, sf_dir))


@query(S._with("handoff", f"e as ({_TURNS})", then="select g.src src1, e.src src2, g.dst dst1, e.dst dst2, string_agg(g.label, ' ' order by g.label) labels from g join e on e.label = g.label group by all"))
def kron_label_sets(spark, sf_dir):
    return kron.label_sets(B.handoff(spark, sf_dir), _turns(spark, sf_dir), sep=" ")


@query(S._with("handoff", f"e as ({_TURNS})", then="select g.label, count(*) n from g join e on e.label = g.label group by g.label"))
def kron_families(spark, sf_dir):
    parts = kron.families(B.handoff(spark, sf_dir).decompose(), _turns(spark, sf_dir).decompose())
    return pt.union_all([df.agg(F.count("*").alias("n")).select(F.lit(k).alias("label"), "n") for k, df in parts.items()]).where("n > 0")


@query(
    "with p as (select event_id, event_type || coalesce(' ' || lead(event_type) over w, '') || coalesce(' ' || lead(event_type, 2) over w, '') word from events window w as (partition by user_id order by ts, event_id)) "
    "select event_id, word from p where word in ('click view', 'click view view')"
)
def fsm_intersection(spark, sf_dir):
    """Words of an event with its user's next two that both expressions accept."""
    m = fa.from_regex("click view*").intersect(fa.from_regex("(click | view) view view?"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    words = load(spark, sf_dir, "events").select("event_id", F.array_compact(F.array("event_type", *[F.lead("event_type", k).over(w) for k in (1, 2)])).alias("w"))
    return words.where(pt.accepts_udf(rsm.from_fsm(m))("w")).select("event_id", F.array_join("w", " ").alias("word"))


@query(S._with("handoff", then="select label, count(*) n from g group by label"))
def decompose(spark, sf_dir):
    return pt.union_all([df.agg(F.count("*").alias("n")).select(F.lit(k).alias("label"), "n") for k, df in B.handoff(spark, sf_dir).decompose().items()])


@query(S._with("handoff", then="select src, label, dst from g"))
def compose(spark, sf_dir):
    return LabeledGraph.compose(B.handoff(spark, sf_dir).label_sets()).edges


@query(S._with("handoff", then="select distinct a.src, b.dst from g a join g b on b.src = a.dst where a.label = 'click' and b.label = 'view'"))
def mxm(spark, sf_dir):
    m = B.handoff(spark, sf_dir).decompose()
    return boolmat.mxm(m["click"], m["view"])


@query(S._with("handoff", then="select distinct dst id from g where src % 10 = 0 and label = 'click'"))
def vxm(spark, sf_dir):
    g = B.handoff(spark, sf_dir)
    return boolmat.vxm(g.vertices.where("id % 10 = 0"), g.select_labels({"click"}).edges)


@query(S._with("ontology", "e as (select src, dst from g where label = 'sco')", "c(src, dst) as (select src, dst from e union select c.src, e.dst from c join e on e.src = c.dst)", then="select src, dst from c"))
def closure_edges(spark, sf_dir):
    e = B.ontology(spark, sf_dir).select_labels({"sco"}).edges.select(F.col("src").alias("x"), F.col("dst").alias("y"))
    return closure.scratch(e, Stage(spark), "squaring")[0].select(F.col("x").alias("src"), F.col("y").alias("dst"))


@query(S._with("ontology", "e as (select src, dst from g where label = 'sco')", "c(src, dst) as (select src, dst from e union select c.src, e.dst from c join e on e.src = c.dst)", then="select src, dst from c"))
def closure_packed(spark, sf_dir):
    e = B.ontology(spark, sf_dir).select_labels({"sco"}).edges.select(F.col("src").alias("x"), F.col("dst").alias("y"))
    rows, _, _ = closure.insert_packed(None, e, Stage(spark))
    return closure.to_pairs(rows).select(F.col("x").alias("src"), F.col("y").alias("dst"))


@query("select cast(event_id % 5 as int) q, event_id u from events")
def flatten_roundtrip(spark, sf_dir):
    n = 1 << 40
    ev = load(spark, sf_dir, "events").select((F.col("event_id") % 5).cast("int").alias("q"), F.col("event_id").cast("long").alias("u"))
    q, u = kron.unflatten(F.col("x"), n)
    return ev.select(kron.flatten(F.col("q").cast("long"), F.col("u"), n).alias("x")).select(q.alias("q"), u.alias("u"))


# --------------------------------------------------------------------------- measures
@query(S._with("ontology", then="select 'vertices' measure, count(*) n from vs union all select 'edges', count(*) from g union all select 'label ' || label, count(*) from g group by label"))
def graph_stats(spark, sf_dir):
    return B.ontology(spark, sf_dir).stats()


@query(S._with("commerce", then="select label, count(*) n, cast(row_number() over (order by count(*) desc, label) as int) rank from g group by label"))
def label_frequency(spark, sf_dir):
    return B.commerce(spark, sf_dir).label_frequency()


#: Grammars over two labels; each event and its user's next bind them.
_BOUND = {
    "anbn": "S -> x y | x S y", "g1": "S -> x~ S x\nS -> y~ S y\nS -> x~ x\nS -> y~ y", "g2": "S -> x~ S x\nS -> x", "geo": "S -> x S x~\nS -> x x~",
    "ma": "S -> x~ V x\nV -> ((S?) y~)* (S?) (y (S?))*", "nullable": "S -> ε | x S y", "ambig": "S -> S S | x", "regular_part": "S -> x S y | z+",
}
_XY = "p as (select event_type x, lead(event_type) over (partition by user_id order by ts, event_id) y from events)"


def _label_pairs(spark, sf_dir) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select(F.col("event_type").alias("x"), F.lead("event_type").over(w).alias("y")).where("y is not null")


@query(
    f"with {_XY} select grammar, grammar_size, boxes, states, cast(count(*) as bigint) n from p join (values ('anbn', false, 7, 1, 4), ('anbn', true, 7, 1, 4), ('g1', false, 14, 1, 6), ('g1', true, 7, 1, 4), ('g2', false, 6, 1, 4), ('g2', true, 6, 1, 4), ('geo', false, 7, 1, 4), ('geo', true, 7, 1, 4)) t(grammar, same, grammar_size, boxes, states) on t.same = (p.x = p.y) group by all"
)
def grammar_sizes(spark, sf_dir):
    out = measure.bound_growth(_label_pairs(spark, sf_dir), {k: _BOUND[k] for k in ("anbn", "g1", "g2", "geo")})
    return out.groupBy("grammar", "grammar_size", "boxes", "states").agg(F.sum("n").alias("n"))


@query(
    f"with {_XY} select grammar, grammar_size, boxes, states, transitions, normal_rules, normal_size, cast(count(*) as bigint) n from p join (values ('anbn', false, 7, 1, 4, 4, 5, 13), ('anbn', true, 7, 1, 4, 4, 4, 11), ('g1', false, 14, 1, 6, 8, 10, 26), ('g1', true, 7, 1, 4, 4, 5, 13), ('g2', false, 6, 1, 4, 4, 5, 12), ('g2', true, 6, 1, 4, 4, 5, 12), ('geo', false, 7, 1, 4, 4, 5, 13), ('geo', true, 7, 1, 4, 4, 5, 13), ('ma', false, 21, 2, 8, 11, 27, 70), ('ma', true, 21, 2, 8, 11, 25, 66), ('nullable', false, 5, 1, 4, 3, 5, 13), ('nullable', true, 5, 1, 4, 3, 4, 11), ('ambig', false, 5, 1, 3, 3, 2, 5), ('ambig', true, 5, 1, 3, 3, 2, 5), ('regular_part', false, 11, 1, 5, 5, 9, 22), ('regular_part', true, 11, 1, 5, 5, 8, 20)) "
    "t(grammar, same, grammar_size, boxes, states, transitions, normal_rules, normal_size) on t.same = (p.x = p.y) group by all"
)
def grammar_growth(spark, sf_dir):
    return measure.bound_growth(_label_pairs(spark, sf_dir), _BOUND)


def iteration_trace(spark, sf_dir):
    return measure.trace(ix.build(B.ontology(spark, sf_dir), machine_of("g1"), strategy="loop").metrics, spark)


register("iteration_trace", iteration_trace)


@query(S.bounded_wrapped("trail", [("click", "purchase")], [("click", "purchase")], 20, then="select count(*) pairs, cast(sum(n) as bigint) walks, avg(n) mean_walks, max(n) most_walks from (select src, dst, count(*) n from s group by src, dst) x"))
def paths_per_pair(spark, sf_dir):
    return measure.paths_per_pair(pt.all_pairs(ix.PathIndex(B.trail(spark, sf_dir), machine_of("anbn", AB), None), 20))


@query(S.linear("g1", "ontology", then="select cast(src % 16 as int) kind_src, cast(dst % 16 as int) kind_dst, count(*) n from (select distinct src, dst from s) x group by cube (cast(src % 16 as int), cast(dst % 16 as int))"))
def cube_kinds(spark, sf_dir):
    return measure.answer_rollup(QUERIES["cf_g1"](spark, sf_dir))


@query("select src, dst, 1 in_a, 1 in_b from (values (1::bigint, 1::bigint)) t(src, dst) where false")
def answers_differ(spark, sf_dir):
    """Both methods on the same classes of twins: whole rectangles differ or agree, so classes are compared, and what
    differs is written out."""
    part, members = twins.reduced(B.territory(spark, sf_dir))
    a, b = ix.build(part, machine_of("geo")).reachable(), baselines.matrix_reach(part, grammar_of("geo")).where("label = 'S'")
    return twins.expand(measure.diff(a, b), members)


@query(S.linear("g1", "ontology", then="select src, count(distinct dst) n from s group by src order by n desc, src limit 10"))
def topk_vertices(spark, sf_dir):
    return QUERIES["cf_g1"](spark, sf_dir).groupBy("src").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "src").limit(10)


# --------------------------------------------------------------------------- surrounding operators
@query(S._with("trail", then="select src, label, dst from g"))
def lead_edges(spark, sf_dir):
    return B.trail(spark, sf_dir).edges


@query("select a.event_id src, 'soon' as label, b.event_id dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 2 hour")
def range_edges(spark, sf_dir):
    return B.range_edges(spark, sf_dir)


_ASOF = "1997-01-01"


@query(f"select o_custkey * 16 + 2 src, 'latest' as label, arg_max(o_orderkey, struct_pack(d := o_orderdate, k := o_orderkey)) * 16 + 5 dst from orders where o_orderdate < timestamp '{_ASOF}' group by o_custkey")
def asof_edges(spark, sf_dir):
    return B.asof_edges(spark, sf_dir, _ASOF)


@query("with l as (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) href from pages) select page_id * 16 + 11 src, count(*) n from l group by page_id")
def href_edges(spark, sf_dir):
    return B.weblinks(spark, sf_dir).select_labels({"links"}).edges.groupBy("src").agg(F.count("*").alias("n"))


@query("select event_id, cast(json_extract(props, '$.k') as int) k from events where cast(json_extract(props, '$.k') as int) < 20")
def json_label(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("int")
    return load(spark, sf_dir, "events").select("event_id", k.alias("k")).where("k < 20")


def _set(op: str, first: str, second: str) -> str:
    def body(text: str) -> tuple[str, str]:
        m = fa.from_regex(text)
        t = ", ".join(f"({q}, '{s}', {p})" for q, s, p in sorted(m.edges))
        return t, ", ".join(map(str, sorted(m.finals)))

    (t1, f1), (t2, f2) = body(first), body(second)
    return S._with(
        "trail", f"t1(q, s, p) as (values {t1})", f"t2(q, s, p) as (values {t2})",
        "r1(src, q, dst) as (select id, 0, id from vs union select r1.src, t1.p, g.dst from r1 join t1 on t1.q = r1.q join g on g.src = r1.dst and g.label = t1.s)",
        "r2(src, q, dst) as (select id, 0, id from vs union select r2.src, t2.p, g.dst from r2 join t2 on t2.q = r2.q join g on g.src = r2.dst and g.label = t2.s)",
        then=f"select src, dst from r1 where q in ({f1}) {op} select src, dst from r2 where q in ({f2})",
    )


def _answers(spark, sf_dir, text):
    return ix.build(B.trail(spark, sf_dir), fa.from_regex(text)).reachable()


register("set_union", lambda s, d: _answers(s, d, _Q2).union(_answers(s, d, _AB_PLUS)).distinct(), _set("union", _Q2, _AB_PLUS))
register("set_intersect", lambda s, d: _answers(s, d, _Q2).intersect(_answers(s, d, _AB_PLUS)), _set("intersect", _Q2, _AB_PLUS))
register("set_except", lambda s, d: _answers(s, d, _AB_PLUS).subtract(_answers(s, d, _Q2)), _set("except", _AB_PLUS, _Q2))


@query("select event_id, count(*) over (partition by user_id order by ts, event_id rows unbounded preceding) running, count(*) over (partition by user_id order by ts, event_id rows 4 preceding) last5, date_diff('second', lag(ts) over (partition by user_id order by ts, event_id), ts) gap_s from events")
def window_running(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    ev = load(spark, sf_dir, "events")
    gap = F.unix_timestamp("ts") - F.unix_timestamp(F.lag("ts").over(w))
    return ev.select("event_id", F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.count("*").over(w.rowsBetween(-4, 0)).alias("last5"), gap.alias("gap_s"))


@query("""with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end fresh from events),
s as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) k from e)
select user_id, min(ts) session_start, max(ts) last_ts, count(*) n from s group by user_id, k""")
def session_trails_q(spark, sf_dir):
    return session_trails(load(spark, sf_dir, "events"))


QUERIES["session_trails"], ORACLE["session_trails"] = QUERIES.pop("session_trails_q"), ORACLE.pop("session_trails_q")


@query("select time_bucket(interval 1 hour, ts) window_start, event_type, count(*) n from events group by all")
def tumbling_labels(spark, sf_dir):
    return windowed_labels(load(spark, sf_dir, "events"), "1 hour")


@query("select time_bucket(interval 30 minute, ts) - to_minutes(30 * k) window_start, event_type, count(*) n from events, range(4) t(k) group by all")
def sliding_labels(spark, sf_dir):
    return windowed_labels(load(spark, sf_dir, "events"), "2 hours", "30 minutes")


@query("with w as (select user_id, string_agg(event_type, ' ' order by ts, event_id) word from events group by user_id) select user_id, regexp_full_match(word, '(.* )?click purchase( .*)?') accepted from w")
def dfa_words_udf(spark, sf_dir):
    from .. import functions

    functions.register(spark)
    ev = load(spark, sf_dir, "events").groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("e"))
    every = "(click | view | purchase | error | signup)*"
    return ev.select("user_id", F.expr(f"lp_accepts('{every} click purchase {every}', transform(e, x -> x.event_type))").alias("accepted"))


@query("select user_id, count(*) filter (event_type = 'click') click, count(*) filter (event_type = 'view') \"view\", count(*) filter (event_type = 'purchase') purchase from events group by user_id")
def pivot_events(spark, sf_dir):
    p = load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1)))
    return p.select("user_id", *[F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in ("click", "view", "purchase")])


@query(S.bounded_words("trail", "click view click", 3))
def recursive_cte(spark, sf_dir):
    B.trail(spark, sf_dir).edges.createOrReplaceTempView("lp_trail_edges")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")  # walks grow with the table; their length ends the recursion
    return spark.sql("""
        with recursive walk(src, dst, len, word) as (
          select src, dst, 1, label from lp_trail_edges where label = 'click'
          union all
          select w.src, e.dst, w.len + 1, w.word || ' ' || e.label from walk w join lp_trail_edges e
          on e.src = w.dst and e.label = case w.len when 1 then 'view' else 'click' end where w.len < 3)
        select src, dst, len, word from walk where len = 3""")


@query(
    f"with {_XY}, d as (select x, y, cast(count(*) as bigint) n from p where y is not null group by x, y) "
    "select x, y, n, 0 q, x symbol, 1 p, true from_start, false to_final from d union all select x, y, n, 1, y, 1, false, false from d union all select x, y, n, 1, 'end', 2, false, true from d"
)
def udtf_transitions(spark, sf_dir):
    """Automata of patterns made from the label pairs of the trails, in a lateral join."""
    from .. import functions

    functions.register(spark)
    _label_pairs(spark, sf_dir).groupBy("x", "y").agg(F.count("*").alias("n")).createOrReplaceTempView("lp_label_pairs")
    return spark.sql("select d.x, d.y, d.n, t.* from lp_label_pairs d, lateral lp_transitions(d.x || ' ' || d.y || '* end') t")


def _session(spark, sf_dir) -> LangPathSession:
    s = LangPathSession(spark)
    for name, build in B.BUILDERS.items():
        s.register(name, lambda b=build: b(spark, sf_dir))
    return s


@query(S.regular("trail", _Q5, "select id from vs where id in (1, 2, 3, 4, 5, 6, 7, 8, 9, 10)"))
def match_reach(spark, sf_dir):
    return _session(spark, sf_dir).sql("MATCH click view* purchase ON trail FROM (1, 2, 3, 4, 5, 6, 7, 8, 9, 10)")


@query(S.linear("geo", "territory", then="select distinct src, dst from s where dst in (19, 35, 51)"))
def match_grammar(spark, sf_dir):
    return _session(spark, sf_dir).sql("MATCH {S -> bt S bt~ | bt bt~} ON territory TO (19, 35, 51)")


@query(S.bounded_words("handoff", "click view", 2, "select src, dst, len, word from r where q in (@finals) and src in (1, 2, 3)"))
def match_paths(spark, sf_dir):
    return _session(spark, sf_dir).sql("MATCH click view ON handoff FROM (1, 2, 3) RETURN paths UP TO 2")


@query(S.linear("anbn", "trail", AB))
def stream_insert(spark, sf_dir):
    """Edges arrive in four batches; the maintained index ends as the batch build does."""
    ev = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    edges = trail_edges(ev)
    start = LabeledGraph(edges.limit(0), ev.select(F.col("event_id").cast("long").alias("id")))
    kept = Maintained(ix.build(start, machine_of("anbn", AB), strategy="loop"))
    for k in range(4):
        kept.batch(edges.where(F.pmod(F.xxhash64("src"), F.lit(4)) == k), k)
    return kept.index.reachable()


def template_bindings(spark, sf_dir):
    """Ten bindings of a template to frequent labels."""
    from .templates import generate

    rows = generate(B.commerce(spark, sf_dir), "q5", 10)
    return spark.createDataFrame(list(enumerate(rows)), "k int, query string")


register("template_bindings", template_bindings)


@query(S._with("dialogue", "u as (select src, dst from g union select dst, src from g)", "c(src, dst) as (select src, dst from u union select c.src, u.dst from c join u on u.src = c.dst)", then="select src, dst from c"))
def undirected(spark, sf_dir):
    """Connected turns: every label forwards and backwards."""
    g = B.dialogue(spark, sf_dir)
    return ix.build(g.undirected(), fa.from_regex("(user | assistant | system)+")).reachable()


@query("select count(*) // count(*) checked from events")
def estimate(spark, sf_dir):
    """The estimate of an answer's size from hashed sources lies near the size itself."""
    g = B.trail(spark, sf_dir)
    m = fa.from_regex(_Q2)
    whole = ix.build(g, m).reachable().count()
    guess = measure.estimate_pairs(lambda some: ix.build(g, m, sources=some).reachable(), g.vertices, 8)
    return spark.createDataFrame([(int(whole / 2 <= guess <= whole * 2),)], "checked long")


# --------------------------------------------------------------------------- further relational operators
_EV = "event_id, user_id, ts, event_type, value"


def _events(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "events").select(*_EV.split(", "))


@query("select a.event_id src, b.event_id dst from events a join events b on a.user_id = b.user_id and date_trunc('day', a.ts) = date_trunc('day', b.ts) and a.value < b.value and a.ts < b.ts")
def theta_join(spark, sf_dir):
    """Rising values of one user on one day: equal keys to meet, the rest as a condition of the join."""
    e = _events(spark, sf_dir).withColumn("day", F.to_date("ts"))
    a, b = e.alias("a"), e.alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.day") == F.col("b.day")) & (F.col("a.value") < F.col("b.value")) & (F.col("a.ts") < F.col("b.ts"))
    return a.join(b, on).select(F.col("a.event_id").alias("src"), F.col("b.event_id").alias("dst"))


@query("select distinct l_orderkey * 16 + 5 src, o_custkey * 16 + 2 dst from lineitem join orders on l_orderkey = o_orderkey")
def shuffle_hash_join(spark, sf_dir):
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    ends = load(spark, sf_dir, "lineitem").select("l_orderkey").join(o.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    return ends.select((F.col("l_orderkey") * 16 + 5).alias("src"), (F.col("o_custkey") * 16 + 2).alias("dst")).distinct()


@query("select l_orderkey * 16 + 5 src, l_partkey * 16 + 4 mid, o_custkey * 16 + 2 dst, count(*) n from lineitem join orders on l_orderkey = o_orderkey group by all")
def sort_merge_join(spark, sf_dir):
    """What an order contains, joined with who placed it."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    both = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy((F.col("l_orderkey") * 16 + 5).alias("src"), (F.col("l_partkey") * 16 + 4).alias("mid"), (F.col("o_custkey") * 16 + 2).alias("dst")).agg(F.count("*").alias("n"))


@query("select event_type, count(distinct user_id) users, count(distinct date_trunc('day', ts)) n_days, count(*) n from events group by event_type")
def distinct_aggregate(spark, sf_dir):
    return _events(spark, sf_dir).groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct(F.to_date("ts")).alias("n_days"), F.count("*").alias("n"))


@query("select event_type, 1::bigint near from events group by event_type")
def approx_distinct(spark, sf_dir):
    """A sketch's count lies within four of its standard errors (0.02) of the exact one."""
    n = _events(spark, sf_dir).groupBy("event_type").agg(F.approx_count_distinct("event_id", 0.02).alias("guess"), F.countDistinct("event_id").alias("n"))
    return n.select("event_type", (F.abs(F.col("guess") - F.col("n")) <= 0.08 * F.col("n")).cast("long").alias("near"))


@query("select event_type, user_id, count(*) n, cast(grouping(event_type) * 2 + grouping(user_id) as bigint) level from events group by rollup (event_type, user_id)")
def rollup_labels(spark, sf_dir):
    return _events(spark, sf_dir).rollup("event_type", "user_id").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


@query("select event_type, cast(date_part('hour', ts) as int) hr, count(*) n from events group by grouping sets ((event_type), (cast(date_part('hour', ts) as int)), ())")
def grouping_sets(spark, sf_dir):
    e = _events(spark, sf_dir).withColumn("hr", F.hour("ts"))
    return e.groupingSets([["event_type"], ["hr"], []], "event_type", "hr").agg(F.count("*").alias("n")).select("event_type", "hr", "n")


@query(
    "select event_id, cast(rank() over w as int) r, cast(dense_rank() over w as int) d, cast(ntile(4) over (partition by user_id order by ts, event_id) as int) q, percent_rank() over w p "
    "from events window w as (partition by user_id order by event_type)"
)
def rankings(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_type")
    quarter = F.ntile(4).over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return _events(spark, sf_dir).select("event_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), quarter.alias("q"), F.percent_rank().over(w).alias("p"))


@query("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 7200000000 preceding and current row) n from events")
def range_frame(spark, sf_dir):
    """Events of a user in the two hours up to each."""
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-7_200_000_000, 0)
    return _events(spark, sf_dir).select("event_id", F.count("*").over(w).alias("n"))


def _bag(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    e = _events(spark, sf_dir)
    return e.where("event_type = 'click'").select("user_id"), e.where("event_type = 'purchase'").select("user_id")


_BAGS = "select user_id from events where event_type = 'click' {} all select user_id from events where event_type = 'purchase'"


def _bag_query(op: str):
    def run(spark, sf_dir):
        a, b = _bag(spark, sf_dir)
        return getattr(a, op)(b)

    return run


register("bag_except", _bag_query("exceptAll"), _BAGS.format("except"))
register("bag_intersect", _bag_query("intersectAll"), _BAGS.format("intersect"))
register("bag_union", _bag_query("unionAll"), _BAGS.format("union"))


_MONTH, _QUARTER = "year(d) * 100 + month(d)", "year(d) * 10 + quarter(d)"


@query(
    f"with d as (select distinct cast(o_orderdate as date) d from orders), e as (select distinct cast({_MONTH} as bigint) * 16 + 12 src, cast({_QUARTER} as bigint) * 16 + 13 dst from d "
    f"union select distinct cast({_QUARTER} as bigint) * 16 + 13, cast(year(d) as bigint) * 16 + 14 from d), up as (select dst src, src dst from e), "
    "r as (select a.src, b.dst from e a join up b on a.dst = b.src), t as (select a.src, b.dst from e a join r x on a.dst = x.src join up b on x.dst = b.src) select distinct src, dst from (select * from r union all select * from t) z"
)
def date_hierarchy(spark, sf_dir):
    """Months and quarters of one level under a common ancestor: the tree month, quarter, year as a graph."""
    d = load(spark, sf_dir, "orders").select(F.to_date("o_orderdate").alias("d")).distinct()
    month, quarter = (F.year("d") * 100 + F.month("d")).cast("long") * 16 + 12, (F.year("d") * 10 + F.quarter("d")).cast("long") * 16 + 13
    edge = lambda a, b: d.select(a.alias("src"), F.lit("bt").alias("label"), b.alias("dst"))
    g = LabeledGraph.of(edge(month, quarter).union(edge(quarter, F.year("d").cast("long") * 16 + 14))).with_inverses()
    return ix.build(g, machine_of("geo")).reachable()


def queries() -> dict[str, Query]:
    return QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLE
