"""Query templates, grammars, and the generator that binds templates to the labels of a graph."""

from __future__ import annotations

import random
import re

from ..graph import LabeledGraph


def _family() -> dict[str, str]:
    letters = "abcde"
    out = {
        "q1": "a*", "q2": "a b*", "q3": "a b* c*", "q5": "a b* c", "q6": "a* b*", "q7": "a b c*", "q8": "a? b*",
        "q12": "(a b)+ | (c d)+", "q13": "(a (b c)*)+ | (d f)+", "q14": "(a b (c d)*)+ (e | f)*", "q15": "(a | b)+ (c | d)+", "q16": "a b (c | d | e)",
    }
    for k in range(2, 6):
        some = " | ".join(letters[:k])
        out[f"q4_{k}"] = f"({some})*"
        out[f"q9_{k}"] = f"({some})+"
        out[f"q10_{k}"] = f"({some}) {'abcdef'[k]}*"
        out[f"q11_{k}"] = " ".join("abcdf"[:k])
    return dict(sorted(out.items(), key=lambda x: [int(n) for n in re.findall(r"\d+", x[0])]))


TEMPLATES = _family()

#: Fixed binding on the trail graph.
TRAIL = {"a": "click", "b": "view", "c": "purchase", "d": "error", "e": "signup", "f": "flagged"}

# The experiments' grammars; x~ is the inverse of x.
GRAMMARS = {
    "g1": "S -> sco~ S sco\nS -> type~ S type\nS -> sco~ sco\nS -> type~ type",
    "g2": "S -> sco~ S sco\nS -> sco",
    "geo": "S -> bt S bt~\nS -> bt bt~",
    "ma": "S -> d~ V d\nV -> ((S?) a~)* (S?) (a (S?))*",
    "anbn": "S -> a b | a S b",
    "nullable": "S -> ε | a S b",
    "ambig": "S -> S S | a",
    "regular_part": "S -> a S b | c+",
}


def bind(text: str, binding: dict[str, str]) -> str:
    """Replace one-letter symbols."""
    return re.sub(r"(?<![A-Za-z0-9_])([a-f])(?![A-Za-z0-9_])", lambda m: binding.get(m.group(1), m.group(1)), text)


def generate(graph: LabeledGraph, template: str, k: int = 10, seed: int = 7, top: int = 12) -> list[str]:
    """``k`` bindings of a template to distinct frequent labels, chosen with a seed; repeated bindings only
    where the graph has too few labels for ``k`` different ones."""
    text = TEMPLATES.get(template, template)
    letters = sorted(set(re.findall(r"(?<![A-Za-z0-9_])([a-f])(?![A-Za-z0-9_])", text)))
    labels = [r["label"] for r in graph.label_frequency().where(f"rank <= {top}").orderBy("rank").collect()]
    rng, out, tries = random.Random(seed), [], 0
    while len(out) < k:
        tries += 1
        pick = [*rng.sample(labels, min(len(labels), len(letters)))]
        pick += [rng.choice(labels) for _ in range(len(letters) - len(pick))]
        q = bind(text, dict(zip(letters, pick, strict=True)))
        if q not in out or tries > 20 * k:
            out.append(q)
    return out
