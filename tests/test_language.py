import re

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from langpath.language import fsm, grammar, regex, rsm
from langpath.workloads.templates import GRAMMARS, TEMPLATES, bind

from .oracles import words

NAMES = {"q1": (1, 1), "q2": (2, 1), "q3": (3, 2), "q5": (3, 1), "q6": (2, 2), "q7": (3, 1), "q8": (2, 2), "q12": (5, 2), "q13": (5, 2), "q14": (5, 2), "q15": (3, 1), "q16": (4, 1), "q11_4": (5, 1), "q9_3": (2, 1), "q10_2": (2, 1), "q4_5": (1, 1)}


@pytest.mark.parametrize("key", sorted(NAMES))
def test_minimal_automata_have_the_known_sizes(key):
    m = fsm.from_regex(TEMPLATES[key])
    assert (m.n, len(m.finals)) == NAMES[key]
    assert m.is_finite() == (key in ("q16", "q11_4"))


@pytest.mark.parametrize("key", sorted(TEMPLATES))
def test_automata_accept_as_the_regular_expression_engine(key):
    text = TEMPLATES[key]
    m, pattern = fsm.from_regex(text), re.compile(text.replace(" ", ""))
    loose = fsm.from_regex(text, deterministic=False)
    for w in words("abc", 5):
        assert m.accepts(list(w)) == bool(pattern.fullmatch("".join(w))) == loose.accepts(list(w))


def test_28_templates_and_bindings():
    assert len(TEMPLATES) == 28
    assert bind("a (b | c)*", {"a": "click", "b": "view", "c": "abc"}) == "click (view | abc)*"


@pytest.mark.parametrize("bad", ["a |* b", "(a", "a)", "*", "a $ b"])
def test_bad_expressions(bad):
    with pytest.raises(ValueError):
        regex.parse(bad)


def test_simplification():
    assert regex.parse("(a*)*") == regex.parse("a*")
    assert regex.parse("∅ a | b ε") == regex.parse("b")
    assert regex.parse("(ε | a)*") == regex.parse("a*")
    assert not fsm.from_regex("∅").accepts([])
    assert fsm.from_regex("ε").accepts([]) and not fsm.from_regex("ε").accepts(["a"])


def test_intersection_and_reversal():
    m = fsm.from_regex("a b*").intersect(fsm.from_regex("(a | b) b"))
    for w in words("ab", 4):
        assert m.accepts(list(w)) == (w == ("a", "b"))
        assert fsm.from_regex("a b* a?").reversed().accepts(list(w)) == fsm.from_regex("a b* a?").accepts(list(w)[::-1])


SIZES = {"anbn": (7, 1, 4), "g1": (14, 1, 6), "g2": (6, 1, 4), "geo": (7, 1, 4)}


@pytest.mark.parametrize("name", sorted(SIZES))
def test_machine_sizes(name):
    g = grammar.parse(GRAMMARS[name])
    m = rsm.from_grammar(g)
    assert (g.size(), len(m.boxes), m.size()) == SIZES[name]


def test_alias_machine():
    m = rsm.from_grammar(GRAMMARS["ma"])
    assert m.size() == 8 and m.nullable() == {"V"} and m.calls == {"S", "V"}


def test_worked_machine_accepts():
    m = rsm.from_grammar(GRAMMARS["anbn"])
    for w in words("ab", 6):
        n = len(w) // 2
        assert m.accepts(list(w)) == (n > 0 and w == ("a",) * n + ("b",) * n)


@pytest.mark.parametrize("text", ["S -> ε | a S b", "S -> S S | a", "S -> A b | b\nA -> S a | ε", "S -> a S b | c+", "S -> (S a)? b", "S -> S a | A\nA -> S b | c"])
def test_three_acceptors_agree(text):
    g = grammar.parse(text)
    m, loose = rsm.from_grammar(g), rsm.from_grammar(g, minimize=False)
    for w in words("abc", 5):
        assert m.accepts(list(w)) == g.derives(list(w)) == loose.accepts(list(w)), w


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.sampled_from("STU"), st.lists(st.sampled_from("STUab"), max_size=3)), min_size=1, max_size=6))
def test_random_grammars(rules):
    text = "\n".join([f"{h} -> {' '.join(b) or 'ε'}" for h, b in rules] + [f"{n} -> ∅" for n in "STU"])
    g = grammar.parse(text, "S")
    m = rsm.from_grammar(g)
    for w in words("ab", 4):
        assert m.accepts(list(w)) == g.derives(list(w))
    for w in words("ab", 3):
        assert m.reversed().accepts(list(w)[::-1]) == g.derives(list(w))
