"""Context-free grammars whose right-hand sides may be regular expressions."""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field
from itertools import product

from . import regex as rx


@dataclass(frozen=True)
class NormalForm:
    """Binary form: A -> B C, A -> t, and the nonterminals that derive the empty word."""

    start: str
    pairs: frozenset[tuple[str, str, str]]
    units: frozenset[tuple[str, str]]  # (nonterminal, terminal)
    nullable: frozenset[str]
    names: frozenset[str] = field(default_factory=frozenset)  # the nonterminals of the grammar itself
    # the same without folding: own rules of a nonterminal, and (A, B) where A derives B alone, A itself included
    own_pairs: frozenset[tuple[str, str, str]] = field(default_factory=frozenset)
    own_units: frozenset[tuple[str, str]] = field(default_factory=frozenset)
    alone: frozenset[tuple[str, str]] = field(default_factory=frozenset)

    def size(self) -> int:
        return 3 * len(self.pairs) + 2 * len(self.units) + len(self.nullable & {self.start})


@dataclass(frozen=True)
class Grammar:
    start: str
    rules: dict[str, rx.Regex]

    @property
    def nonterminals(self) -> set[str]:
        return set(self.rules)

    @property
    def terminals(self) -> set[str]:
        return set().union(*(r.symbols() for r in self.rules.values())) - self.nonterminals

    def productions(self) -> list[tuple[str, rx.Regex]]:
        """Alternatives as single productions."""
        return [(n, p) for n, r in self.rules.items() for p in (r.parts if r.kind == "alt" else (r,))]

    def size(self) -> int:
        """Sum of 1 + length over the productions of the flattened grammar."""
        return sum(1 + len(body) for _, body in self.plain())

    def plain(self) -> list[tuple[str, tuple[str, ...]]]:
        """Productions without operators; each inner choice or repetition gets a nonterminal."""
        out: list[tuple[str, tuple[str, ...]]] = []
        made: dict[rx.Regex, str] = {}

        def bodies(node: rx.Regex) -> list[tuple[str, ...]]:
            match node.kind:
                case "none":
                    return []
                case "eps":
                    return [()]
                case "sym":
                    return [(node.name,)]
                case "alt":
                    return [b for p in node.parts for b in bodies(p)]
                case "cat":
                    return [tuple(x.name if x.kind == "sym" else helper(x) for x in node.parts)]
            return [(helper(node),)]

        def helper(node: rx.Regex) -> str:
            if node not in made:
                name = made[node] = f"_{len(made)}"
                if node.kind == "star":
                    out.append((name, ()))
                    out.extend((name, (*b, name)) for b in bodies(node.parts[0]) if b)
                else:
                    out.extend((name, b) for b in bodies(node))
            return made[node]

        for n, r in self.rules.items():
            for b in bodies(r):
                out.append((n, b))
        return list(dict.fromkeys(out))

    def to_binary_normal_form(self) -> NormalForm:
        """Binary rules; empty and single-nonterminal productions are folded away."""
        rules: set[tuple[str, tuple[str, ...]]] = set()
        inner = set(self.nonterminals)
        plain = self.plain()
        inner |= {n for n, _ in plain}
        for n, body in plain:
            if len(body) > 1:
                body = tuple(s if s in inner else f"<{s}>" for s in body)
                rules |= {(f"<{s}>", (s,)) for _, b in plain if len(b) > 1 for s in b if s not in inner}
            while len(body) > 2:
                tail = "<" + " ".join(body[1:]) + ">"
                rules.add((n, (body[0], tail)))
                n, body = tail, body[1:]
            rules.add((n, body))
        names = {n for n, _ in rules} | inner
        null: set[str] = set()
        while new := {n for n, b in rules if n not in null and all(s in null for s in b)}:
            null |= new
        short = {(n, tuple(s for s, k in zip(b, pick, strict=True) if k)) for n, b in rules for pick in product(*(((1, 0) if s in null else (1,)) for s in b))}
        same = {(n, b[0]) for n, b in short if len(b) == 1 and b[0] in names}
        reach: dict[str, set[str]] = {n: {n} for n in names}
        changed = True
        while changed:
            changed = False
            for a, b in same:
                for r in reach.values():
                    if a in r and b not in r:
                        r.add(b)
                        changed = True
        pairs = {(n, b[0], b[1]) for n in names for m in reach[n] for k, b in short if k == m and len(b) == 2}
        units = {(n, b[0]) for n in names for m in reach[n] for k, b in short if k == m and len(b) == 1 and b[0] not in names}
        own_pairs = frozenset((n, b[0], b[1]) for n, b in short if len(b) == 2)
        own_units = frozenset((n, b[0]) for n, b in short if len(b) == 1 and b[0] not in names)
        alone = frozenset((n, m) for n in names for m in reach[n])
        return NormalForm(self.start, frozenset(pairs), frozenset(units), frozenset(null), frozenset(self.nonterminals), own_pairs, own_units, alone)

    def derives(self, word: list[str]) -> bool:
        """Membership by a table over the binary normal form."""
        nf = self.to_binary_normal_form()
        if not word:
            return self.start in nf.nullable
        n = len(word)
        cell: dict[tuple[int, int], set[str]] = defaultdict(set)
        for i, t in enumerate(word):
            cell[i, i + 1] = {a for a, s in nf.units if s == t}
        for width in range(2, n + 1):
            for i in range(n - width + 1):
                for k in range(i + 1, i + width):
                    cell[i, i + width] |= {a for a, b, c in nf.pairs if b in cell[i, k] and c in cell[k, i + width]}
        return self.start in cell[0, n]


def parse(text: str, start: str | None = None) -> Grammar:
    """Rules ``N -> body`` or ``N : body``, one a line or separated by ``;``; a nonterminal may have several."""
    rules: dict[str, list[rx.Regex]] = {}
    for line in text.replace(";", "\n").splitlines():
        line = line.split("#")[0].strip()
        if not line:
            continue
        head, sep, body = line.partition("->" if "->" in line else ":")
        if not sep or not head.strip().isidentifier():
            raise ValueError(f"not a rule: {line!r}")
        rules.setdefault(head.strip(), []).append(rx.parse(body))
    if not rules:
        raise ValueError("no rules")
    first = start or next(iter(rules))
    if first not in rules:
        raise ValueError(f"no rule for {first}")
    return Grammar(first, {n: rx.alt(*parts) for n, parts in rules.items()})
