"""Predicates over axes: parsing, normal form and tightening.

The tree has four kinds of nodes: ``And``/``Or`` with children, ``Atom`` (an axis against a
value) and ``Opaque`` (anything that positions can't decide, e.g. a test of a variable).
Negations are pushed into the atoms while the tree is built, so none remains in it.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from datetime import date, datetime
from itertools import product
from typing import Any

from gridlake.model import ABOVE, BELOW, Clause, GridSpec, after, before

#: Of each comparison: its complement, and what it is with its sides exchanged.
COMPLEMENT = {"=": "<>", "<>": "=", "<": ">=", ">=": "<", ">": "<=", "<=": ">"}
MIRROR = {"=": "=", "<>": "<>", "<": ">", ">": "<", "<=": ">=", ">=": "<="}


@dataclass(frozen=True)
class Atom:
    axis: str
    op: str
    value: Any


@dataclass(frozen=True)
class Opaque:
    """Kept as text; true as far as boxes are concerned."""

    text: str
    negated: bool = False


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


class TooManyClauses(Exception):
    """The disjunctive normal form exceeds its guard."""


_TOKEN = re.compile(
    r"""\s*(?:(?P<string>'(?:[^']|'')*')|(?P<number>[+-]?(?:\d+\.?\d*|\.\d+)(?:[eE][+-]?\d+)?)
    |(?P<name>[A-Za-z_][A-Za-z_0-9]*)|(?P<op><=|>=|<>|!=|==|=|<|>)|(?P<sign>[(),*/+%-]))""",
    re.X,
)


def _tokens(text: str) -> list[tuple[str, str, int, int]]:
    out, at = [], 0
    while text[at:].strip():
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"can't read the predicate at: {text[at:at + 20]!r}")
        out.append((m.lastgroup, m[m.lastgroup], m.start(m.lastgroup), m.end()))
        at = m.end()
    return out


class _Reader:
    """Recursive descent; ``negated`` is carried down, so the tree comes out without NOT."""

    def __init__(self, text: str, types: dict[str, str]):
        self.text, self.types, self.tokens, self.at = text, types, _tokens(text), 0

    def peek(self, ahead: int = 0) -> tuple[str, str]:
        i = self.at + ahead
        return self.tokens[i][:2] if i < len(self.tokens) else ("end", "")

    def word(self, *names: str) -> bool:
        kind, text = self.peek()
        if kind == "name" and text.upper() in names:
            self.at += 1
            return True
        return False

    def sign(self, text: str) -> bool:
        if self.peek() == ("sign", text):
            self.at += 1
            return True
        return False

    def disjunction(self, negated: bool):
        parts = [self.conjunction(negated)]
        while self.word("OR"):
            parts.append(self.conjunction(negated))
        return parts[0] if len(parts) == 1 else (And if negated else Or)(tuple(parts))

    def conjunction(self, negated: bool):
        parts = [self.negation(negated)]
        while self.word("AND"):
            parts.append(self.negation(negated))
        return parts[0] if len(parts) == 1 else (Or if negated else And)(tuple(parts))

    def negation(self, negated: bool):
        if self.word("NOT"):
            return self.negation(not negated)
        start = self.at
        if self.peek() == ("sign", "("):
            self.at += 1
            try:
                inner = self.disjunction(negated)
                closed = self.sign(")")
            except ValueError:
                closed = False
            if closed and (self.peek()[0] == "end" or self.peek() == ("sign", ")") or self.peek()[1].upper() in ("AND", "OR")):
                return inner
            self.at = start
        return self.comparison(negated)

    def literal(self, axis: str):
        kind, text = self.peek()
        if kind == "name" and text.upper() in ("TIMESTAMP", "DATE", "TIMESTAMP_NTZ") and self.peek(1)[0] == "string":
            self.at += 1
            kind, text = self.peek()
        if kind not in ("string", "number"):
            raise ValueError("not a literal")
        self.at += 1
        return typed(text, kind, self.types[axis])

    def comparison(self, negated: bool):
        start = self.at
        try:
            return self.axis_test(negated)
        except (ValueError, KeyError):
            self.at = start
        return self.opaque(negated)

    def axis_test(self, negated: bool):
        kind, name = self.peek()
        if kind in ("string", "number"):  # a literal on the left
            op = self.peek(1)[1]
            axis = self.peek(2)[1]
            if self.peek(1)[0] != "op" or axis not in self.types:
                raise ValueError("no axis")
            value = typed(name, kind, self.types[axis])
            self.at += 3
            self.ends()
            return atom(axis, MIRROR[_plain(op)], value, negated)
        if kind != "name" or name not in self.types:
            raise ValueError("no axis")
        self.at += 1
        if self.peek()[0] == "op":
            op = _plain(self.peek()[1])
            self.at += 1
            out = atom(name, op, self.literal(name), negated)
            self.ends()
            return out
        flip = self.word("NOT") ^ negated
        if self.word("BETWEEN"):
            lo = self.literal(name)
            if not self.word("AND"):
                raise ValueError("BETWEEN without AND")
            parts = (atom(name, ">=", lo, flip), atom(name, "<=", self.literal(name), flip))
            self.ends()
            return Or(parts) if flip else And(parts)
        if self.word("IN"):
            if not self.sign("("):
                raise ValueError("IN without a list")
            items = [self.literal(name)]
            while self.sign(","):
                items.append(self.literal(name))
            if not self.sign(")"):
                raise ValueError("the list doesn't end")
            self.ends()
            parts = tuple(atom(name, "=", v, flip) for v in items)
            return parts[0] if len(parts) == 1 else (And if flip else Or)(parts)
        raise ValueError("no test of an axis")

    def ends(self) -> None:
        """A test must be followed by a connective; else it is part of a larger expression."""
        kind, text = self.peek()
        if not (kind == "end" or (kind, text) == ("sign", ")") or kind == "name" and text.upper() in ("AND", "OR")):
            raise ValueError("goes on")

    def opaque(self, negated: bool) -> Opaque:
        """Everything up to the next connective on this level; BETWEEN takes its AND along."""
        start, depth, between = self.at, 0, False
        while self.at < len(self.tokens):
            kind, text = self.peek()
            upper = text.upper() if kind == "name" else ""
            if (kind, text) == ("sign", ")") and not depth:
                break
            depth += ((kind, text) == ("sign", "(")) - ((kind, text) == ("sign", ")"))
            if not depth and upper == "AND" and between:
                between = False
            elif not depth and upper in ("AND", "OR"):
                break
            between |= upper == "BETWEEN"
            self.at += 1
        if start == self.at:
            raise ValueError(f"can't read the predicate near token {start}")
        return Opaque(self.text[self.tokens[start][2] : self.tokens[self.at - 1][3]], negated)


def _plain(op: str) -> str:
    return {"!=": "<>", "==": "="}.get(op, op)


def typed(text: str, kind: str, dtype: str):
    """A literal as the axis' type."""
    body = text[1:-1].replace("''", "'") if kind == "string" else text
    if dtype.startswith("timestamp"):
        got = datetime.fromisoformat(body)
        return got
    if dtype == "date":
        return date.fromisoformat(body)
    if dtype == "string":
        if kind != "string":
            raise ValueError("a string axis needs a string")
        return body
    return float(body)


def atom(axis: str, op: str, value, negated: bool = False) -> Atom:
    return Atom(axis, COMPLEMENT[op] if negated else op, value)


def parse_predicate(text: str, spec: GridSpec):
    """The tree of a WHERE text; axes can be named by value or, as ``<axis>_ix``, by position."""
    types = {a.name: a.dtype for a in spec.axes} | {a.ix: "int" for a in spec.inner}
    reader = _Reader(text, types)
    tree = reader.disjunction(False)
    if reader.at < len(reader.tokens):
        raise ValueError(f"can't read the predicate behind token {reader.at}")
    return tree


def split_equalities(tree):
    """Equalities as two inequalities, inequalities of the other kind as a disjunction."""
    if isinstance(tree, And | Or):
        return type(tree)(tuple(map(split_equalities, tree.parts)))
    if isinstance(tree, Atom) and tree.op == "=":
        return And((Atom(tree.axis, ">=", tree.value), Atom(tree.axis, "<=", tree.value)))
    if isinstance(tree, Atom) and tree.op == "<>":
        return Or((Atom(tree.axis, "<", tree.value), Atom(tree.axis, ">", tree.value)))
    return tree


def clause_count(tree) -> int:
    """Conjunctions that the disjunctive normal form would have."""
    if isinstance(tree, Or):
        return sum(map(clause_count, tree.parts))
    if isinstance(tree, And):
        out = 1
        for p in tree.parts:
            out *= clause_count(p)
        return out
    return 1


def to_dnf(tree, max_clauses: int = 4096) -> list[tuple[Atom, ...]]:
    """Conjunctions of atoms; opaque tests are left out, as they are applied to the rows."""
    if clause_count(tree) > max_clauses:
        raise TooManyClauses(clause_count(tree))

    def expand(node) -> list[tuple[Atom, ...]]:
        if isinstance(node, Or):
            return [c for p in node.parts for c in expand(p)]
        if isinstance(node, And):
            return [sum(cs, ()) for cs in product(*map(expand, node.parts))]
        return [(node,)] if isinstance(node, Atom) else [()]

    return expand(tree)


def range_of(a: Atom):
    """The cuts that an inequality stands for."""
    return {"<": (BELOW, before(a.value)), "<=": (BELOW, after(a.value)), ">": (after(a.value), ABOVE), ">=": (before(a.value), ABOVE)}[a.op]


def tighten(atoms: tuple[Atom, ...]) -> Clause | None:
    """The tightest range on every axis; None if two atoms contradict each other."""
    clause = Clause()
    for a in atoms:
        clause = clause.cut(a.axis, *range_of(a))
    return None if clause.empty else clause


def hull_clause(tree) -> Clause:
    """One clause that holds wherever the tree does, found without expanding it."""

    def ranges(node) -> dict:
        if isinstance(node, Atom):
            return {node.axis: range_of(node)} if node.op not in ("=", "<>") else ranges(split_equalities(node))
        if isinstance(node, Opaque):
            return {}
        subs = [ranges(p) for p in node.parts]
        if isinstance(node, And):
            out: dict = {}
            for s in subs:
                for axis, (lo, hi) in s.items():
                    a, b = out.get(axis, (BELOW, ABOVE))
                    out[axis] = (max(a, lo), min(b, hi))
            return out
        common = set.intersection(*(set(s) for s in subs))
        return {axis: (min(s[axis][0] for s in subs), max(s[axis][1] for s in subs)) for axis in common}

    return Clause(ranges(tree))


def clauses_of(tree, max_clauses: int = 4096) -> list[Clause]:
    """The tightened clauses of a predicate; beyond the guard its hull alone."""
    try:
        found = [tighten(c) for c in to_dnf(split_equalities(tree), max_clauses)]
    except TooManyClauses:
        hull = hull_clause(tree)
        return [] if hull.empty else [hull]
    return [c for c in found if c is not None]


def decided(tree, max_clauses: int = 4096) -> bool:
    """Whether boxes alone decide the predicate: every test is one of an axis, and the
    expansion stays within its guard."""

    def plain(node) -> bool:
        return all(map(plain, node.parts)) if isinstance(node, And | Or) else isinstance(node, Atom)

    return plain(tree) and clause_count(split_equalities(tree)) <= max_clauses


def to_sql(tree) -> str:
    """The tree as SQL again."""
    if isinstance(tree, And | Or):
        return "(" + (" AND " if isinstance(tree, And) else " OR ").join(map(to_sql, tree.parts)) + ")"
    if isinstance(tree, Opaque):
        return f"(NOT ({tree.text}))" if tree.negated else f"({tree.text})"
    value = tree.value
    text = f"TIMESTAMP_NTZ '{value}'" if isinstance(value, datetime) else f"DATE '{value}'" if isinstance(value, date) else "'" + value.replace("'", "''") + "'" if isinstance(value, str) else f"CAST({value!r} AS DOUBLE)"
    return f"({tree.axis} {tree.op} {text})"
