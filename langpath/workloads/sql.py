"""The same questions in ANSI SQL, for an engine with recursive common table expressions.

Every graph is a CTE ``g(src, label, dst)`` with ``vs(id)`` beside it; queries are put behind it."""

from __future__ import annotations

from ..language import fsm as fa
from ..sources.builders import BRANDS, KINDS, SIZES


def _vid(key: str, kind: str) -> str:
    return f"(cast({key} as bigint) * 16 + {KINDS[kind]})"


def _inverse(base: str) -> str:
    return f"select src, label, dst from {base} union select dst, label || '~', src from {base}"


_LATTICE = " union ".join(f"select {_vid('i', kind)}, 'sco', {_vid(f'i // {d}', kind)} from range(1, {top + 1}) t(i)" for kind, top in (("brand", BRANDS), ("size", SIZES)) for d in (2, 3))

GRAPHS = {
    "trail": """
e0 as (select event_id, event_type, lead(event_id) over (partition by user_id order by ts, event_id) nxt,
              cast(json_extract(props, '$.k') as int) k from events),
g as (select event_id src, event_type label, nxt dst from e0 where nxt is not null
      union select event_id, 'flagged', nxt from e0 where nxt is not null and k < 20),
vs as (select event_id id from events)""",
    "handoff": """
g as (select distinct cast(user_id as bigint) src, event_type label, cast(nxt as bigint) dst
      from (select user_id, event_type, lead(user_id) over (order by ts, event_id) nxt from events) t where nxt is not null),
vs as (select distinct cast(user_id as bigint) id from events)""",
    "ontology": f"""
h as (select {_vid("p_partkey", "part")} src, 'type' label, {_vid("replace(p_brand, 'Brand#', '')", "brand")} dst from part
      union select {_vid("p_partkey", "part")}, 'type', {_vid("p_size", "size")} from part
      union select {_vid("c_custkey", "customer")}, 'type', {_vid("c_nationkey", "nation")} from customer
      union select {_vid("s_suppkey", "supplier")}, 'type', {_vid("s_nationkey", "nation")} from supplier
      union select {_vid("n_nationkey", "nation")}, 'sco', {_vid("n_regionkey", "region")} from nation
      union {_LATTICE}),
g as ({_inverse("h")}),
vs as (select src id from g union select dst from g)""",
    "pointer": f"""
o as (select * from orders where o_orderpriority = '1-URGENT'),
h as (select {_vid("o_orderkey", "order")} src, 'd' label, {_vid("o_custkey", "customer")} dst from o
      union select {_vid("c_custkey", "customer")}, 'd', {_vid("c_nationkey", "nation")} from customer
      union select {_vid("n_nationkey", "nation")}, 'd', {_vid("n_regionkey", "region")} from nation
      union select {_vid("o_orderkey", "order")}, 'a', {_vid("nxt", "order")}
            from (select o_orderkey, lead(o_orderkey) over (partition by o_orderdate order by o_orderkey) nxt from o) t where nxt is not null),
g as ({_inverse("h")}),
vs as (select {_vid("o_orderkey", "order")} id from o union select {_vid("c_custkey", "customer")} from customer
       union select {_vid("n_nationkey", "nation")} from nation union select {_vid("r_regionkey", "region")} from region)""",
    "dialogue": """
c0 as (select conv_id, turn, role, lead(turn) over (partition by conv_id order by turn) nxt from conversations),
g as (select distinct conv_id * 16 + turn src, role label, conv_id * 16 + nxt dst from c0 where nxt is not null),
vs as (select distinct conv_id * 16 + turn id from conversations)""",
    "weblinks": f"""
l0 as (select distinct page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) href from pages)""",
    "commerce": f"""
g as (select {_vid("l_orderkey", "order")} src, 'contains' label, {_vid("l_partkey", "part")} dst from lineitem
      union select {_vid("l_orderkey", "order")}, 'shipped_by', {_vid("l_suppkey", "supplier")} from lineitem
      union select {_vid("l_partkey", "part")}, 'sold_by', {_vid("l_suppkey", "supplier")} from lineitem
      union select {_vid("o_orderkey", "order")}, 'placed_by', {_vid("o_custkey", "customer")} from orders
      union select {_vid("c_custkey", "customer")}, 'located', {_vid("c_nationkey", "nation")} from customer
      union select {_vid("s_suppkey", "supplier")}, 'located', {_vid("s_nationkey", "nation")} from supplier
      union select {_vid("n_nationkey", "nation")}, 'within', {_vid("n_regionkey", "region")} from nation),
vs as (select src id from g union select dst from g)""",
}
for _full in (False, True):
    GRAPHS["territory_full" if _full else "territory"] = f"""
h as (select {_vid("s_suppkey", "supplier")} src, 'bt' label, {_vid("s_nationkey", "nation")} dst from supplier
      union select {_vid("n_nationkey", "nation")}, 'bt', {_vid("n_regionkey", "region")} from nation
      {f"union select {_vid('c_custkey', 'customer')}, 'bt', {_vid('c_nationkey', 'nation')} from customer" if _full else ""}),
g as ({_inverse("h")}),
vs as (select src id from g union select dst from g)"""


def _with(graph: str, *ctes: str, then: str) -> str:
    return "with recursive " + ",\n".join([GRAPHS.get(graph, graph).strip(), *ctes]) + "\n" + then


def regular(graph: str, text: str, sources: str | None = None, columns: str = "src, dst") -> str:
    """Product of the automaton (a list of values) and the graph, closed by UNION."""
    m = fa.from_regex(text)
    start = next(iter(m.starts))
    t = ", ".join(f"({q}, '{s}', {p})" for q, s, p in sorted(m.edges)) or "(-1, '', -1)"
    from_ = sources or "select id from vs"
    finals = ", ".join(map(str, sorted(m.finals))) or "-1"
    return _with(
        graph,
        f"t(q, s, p) as (values {t})",
        f"srcs as ({from_})",
        f"r(src, q, dst) as (select id, {start}, id from srcs union select r.src, t.p, g.dst from r join t on t.q = r.q join g on g.src = r.dst and g.label = t.s)",
        then=f"select distinct {columns} from r where q in ({finals})",
    )


def wrapped(graph: str, base: str, around: list[tuple[str, str]], then: str = "select distinct src, dst from s") -> str:
    """Linear grammar: base pairs, wrapped again and again by a label on either side."""
    steps = " union ".join(f"select a.src, b.dst from s join g a on a.dst = s.src and a.label = '{x}' join g b on b.src = s.dst and b.label = '{y}'" for x, y in around)
    if len(around) > 1:
        pairs = ", ".join(f"('{x}', '{y}')" for x, y in around)
        steps = f"select a.src, b.dst from s join g a on a.dst = s.src join g b on b.src = s.dst join w on w.x = a.label and w.y = b.label"
        return _with(graph, f"w(x, y) as (values {pairs})", f"s(src, dst) as ({base} union {steps})", then=then)
    return _with(graph, f"s(src, dst) as ({base} union {steps})", then=then)


def two(x: str, y: str) -> str:
    return f"select a.src, b.dst from g a join g b on b.src = a.dst where a.label = '{x}' and b.label = '{y}'"


def one(x: str) -> str:
    return f"select src, dst from g where label = '{x}'"


def linear(name: str, graph: str, binding: dict[str, str] | None = None, then: str = "select distinct src, dst from s") -> str:
    b = binding or {"a": "a", "b": "b", "c": "c"}
    match name:
        case "anbn":
            return wrapped(graph, two(b["a"], b["b"]), [(b["a"], b["b"])], then)
        case "nullable":
            return wrapped(graph, "select id, id from vs", [(b["a"], b["b"])], then)
        case "g1":
            return wrapped(graph, two("sco~", "sco") + " union " + two("type~", "type"), [("sco~", "sco"), ("type~", "type")], then)
        case "g2":
            return wrapped(graph, one("sco"), [("sco~", "sco")], then)
        case "geo":
            return wrapped(graph, two("bt", "bt~"), [("bt", "bt~")], then)
        case "regular_part":
            plus = _with(graph, f"c(src, dst) as (select src, dst from g where label = '{b['c']}' union select c.src, g.dst from c join g on g.src = c.dst and g.label = '{b['c']}')", then="")
            steps = f"select a.src, z.dst from s join g a on a.dst = s.src and a.label = '{b['a']}' join g z on z.src = s.dst and z.label = '{b['b']}'"
            return plus.rstrip() + f",\ns(src, dst) as (select src, dst from c union {steps})\n{then}"
    raise KeyError(name)


#: Alias analysis: the graph has three levels of ``d`` and ``a`` joins orders only, so each level follows from the one before.
MA = """v0 as (select id src, id dst from vs where id % 16 = 5
       union select a.src, b.dst from (select o1.o_orderkey * 16 + 5 src, o2.o_orderkey * 16 + 5 dst from o o1 join o o2 on o1.o_orderdate = o2.o_orderdate) a join vs on vs.id = a.src join (select id dst from vs) b on b.dst = a.dst),
s1 as (select distinct a.dst src, b.dst from v0 join g a on a.src = v0.src and a.label = 'd' join g b on b.src = v0.dst and b.label = 'd'),
v1 as (select id src, id dst from vs where id % 16 = 2 union select src, dst from s1),
s2 as (select distinct a.dst src, b.dst from v1 join g a on a.src = v1.src and a.label = 'd' join g b on b.src = v1.dst and b.label = 'd'),
v2 as (select id src, id dst from vs where id % 16 = 1 union select src, dst from s2),
s3 as (select distinct a.dst src, b.dst from v2 join g a on a.src = v2.src and a.label = 'd' join g b on b.src = v2.dst and b.label = 'd'),
v3 as (select id src, id dst from vs where id % 16 = 0 union select src, dst from s3)"""


def alias(box: str) -> str:
    parts = ("s1", "s2", "s3") if box == "S" else ("v0", "v1", "v2", "v3")
    return _with("pointer", MA, then=" union ".join(f"select src, dst from {p}" for p in parts))


def bounded_words(graph: str, text: str, length: int, then: str | None = None) -> str:
    """All accepted walks up to a length, with their words (walks with the same vertices and word are one)."""
    m = fa.from_regex(text)
    t = ", ".join(f"({q}, '{s}', {p})" for q, s, p in sorted(m.edges))
    finals = ", ".join(map(str, sorted(m.finals)))
    return _with(
        graph,
        f"t(q, s, p) as (values {t})",
        f"""r(src, q, dst, len, word, way) as (select id, {next(iter(m.starts))}, id, 0, '', cast(id as varchar) from vs
  union all select r.src, t.p, g.dst, r.len + 1, case when r.len = 0 then g.label else r.word || ' ' || g.label end, r.way || ',' || g.dst
  from r join t on t.q = r.q join g on g.src = r.dst and g.label = t.s where r.len < {length})""",
        then=then or f"select src, dst, len, word from r where q in ({finals})",
    ).replace("@finals", finals)


def bounded_wrapped(graph: str, base: list[tuple[str, ...]], around: list[tuple[str, str]], length: int, then: str = "select src, dst, len, word from s") -> str:
    """The same for a linear grammar: words grow by a label on either side."""
    firsts = []
    for w in base:
        if len(w) == 2:
            firsts.append(f"select a.src, b.dst, 2 len, '{w[0]} {w[1]}' word, a.src || ',' || a.dst || ',' || b.dst way from g a join g b on b.src = a.dst where a.label = '{w[0]}' and b.label = '{w[1]}'")
        else:
            firsts.append(f"select src, dst, 1, '{w[0]}', src || ',' || dst from g where label = '{w[0]}'")
    pairs = ", ".join(f"('{x}', '{y}')" for x, y in around)
    return _with(
        graph,
        f"w(x, y) as (values {pairs})",
        f"""s(src, dst, len, word, way) as ({" union ".join(firsts)}
  union select a.src, b.dst, s.len + 2, a.label || ' ' || s.word || ' ' || b.label, a.src || ',' || s.way || ',' || b.dst
  from s join g a on a.dst = s.src join g b on b.src = s.dst join w on w.x = a.label and w.y = b.label where s.len + 2 <= {length})""",
        then=then,
    )
