"""Regular expressions over label symbols.

Syntax: juxtaposition or ``.``, ``|``, ``*``, ``+``, ``?``, parentheses, ``ε`` (or ``eps``) and ``∅``.  A symbol
is a name, with ``~`` behind it for the inverse relation."""

from __future__ import annotations

import re
from dataclasses import dataclass


@dataclass(frozen=True)
class Regex:
    """A node: kind is one of sym, eps, none, cat, alt, star."""

    kind: str
    name: str = ""
    parts: tuple[Regex, ...] = ()

    def symbols(self) -> set[str]:
        return {self.name} if self.kind == "sym" else set().union(*(p.symbols() for p in self.parts), set())

    def nullable(self) -> bool:
        match self.kind:
            case "eps" | "star":
                return True
            case "cat":
                return all(p.nullable() for p in self.parts)
            case "alt":
                return any(p.nullable() for p in self.parts)
        return False

    def reversed(self) -> Regex:
        """The expression of the reversed words."""
        parts = tuple(p.reversed() for p in self.parts)
        return Regex(self.kind, self.name, parts[::-1] if self.kind == "cat" else parts)

    def size(self) -> int:
        """Symbol occurrences."""
        return 1 if self.kind == "sym" else sum(p.size() for p in self.parts)

    def __str__(self) -> str:
        match self.kind:
            case "sym":
                return self.name
            case "eps":
                return "ε"
            case "none":
                return "∅"
            case "star":
                return f"({self.parts[0]})*"
            case "cat":
                return " ".join(f"({p})" if p.kind == "alt" else str(p) for p in self.parts)
        return " | ".join(map(str, self.parts))


EPSILON, NOTHING = Regex("eps"), Regex("none")


def symbol(name: str) -> Regex:
    return Regex("sym", name)


def cat(*parts: Regex) -> Regex:
    """Concatenation, folded: ∅ absorbs, ε vanishes."""
    flat: list[Regex] = []
    for p in parts:
        flat.extend(p.parts if p.kind == "cat" else [p])
    if NOTHING in flat:
        return NOTHING
    flat = [p for p in flat if p != EPSILON]
    return EPSILON if not flat else flat[0] if len(flat) == 1 else Regex("cat", parts=tuple(flat))


def alt(*parts: Regex) -> Regex:
    """Union, folded: ∅ vanishes, repeated alternatives are one."""
    flat: list[Regex] = []
    for p in parts:
        flat.extend(p.parts if p.kind == "alt" else [p])
    flat = list(dict.fromkeys(p for p in flat if p != NOTHING))
    return NOTHING if not flat else flat[0] if len(flat) == 1 else Regex("alt", parts=tuple(flat))


def star(part: Regex) -> Regex:
    """Repetition, folded: (x*)* = x*, ε* = ∅* = ε, (ε|x)* = x*."""
    if part.kind == "star":
        return part
    if part.kind == "alt":
        part = alt(*(p for p in part.parts if p != EPSILON))
    return EPSILON if part in (EPSILON, NOTHING) else Regex("star", parts=(part,))


_TOKEN = re.compile(r"\s*(?:([A-Za-z_][A-Za-z0-9_]*~?)|([ε∅|()*+?.]))")


def parse(text: str) -> Regex:
    tokens: list[str] = []
    at = 0
    text = text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"unexpected {text[at:]!r} in {text!r}")
        tokens.append(m.group(1) or m.group(2))
        at = m.end()
    pos = 0

    def peek() -> str | None:
        return tokens[pos] if pos < len(tokens) else None

    def union() -> Regex:
        nonlocal pos
        parts = [sequence()]
        while peek() == "|":
            pos += 1
            parts.append(sequence())
        return alt(*parts)

    def sequence() -> Regex:
        nonlocal pos
        parts = []
        while (t := peek()) is not None and t not in "|)":
            if t == ".":
                pos += 1
                continue
            parts.append(repeated())
        return cat(*parts)

    def repeated() -> Regex:
        nonlocal pos
        node = atom()
        while (t := peek()) in ("*", "+", "?"):
            pos += 1
            node = star(node) if t == "*" else cat(node, star(node)) if t == "+" else alt(node, EPSILON)
        return node

    def atom() -> Regex:
        nonlocal pos
        t = peek()
        pos += 1
        if t == "(":
            node = union()
            if peek() != ")":
                raise ValueError(f"missing ) in {text!r}")
            pos += 1
            return node
        if t is None or t in "|)*+?":
            raise ValueError(f"unexpected {t!r} in {text!r}")
        return EPSILON if t in ("ε", "eps") else NOTHING if t == "∅" else symbol(t)

    out = union()
    if pos != len(tokens):
        raise ValueError(f"unexpected {tokens[pos]!r} in {text!r}")
    return out
