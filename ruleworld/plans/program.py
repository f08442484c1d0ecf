"""Programs of weighted rules: declarations, text form, clauses and checks.

Text form, one statement a line, ``#`` begins a comment::

    @closed cites(doc bigint, doc bigint)        # absent rows are false
    @open   topic(doc bigint, cls int)           # absent rows are no atoms; truth 1, 0 or -1 (unknown)
    5:    topic(d, a) & topic(d, b) => a = b
    -1:   topic(d, 0)
    hard: doc(d) => exists c: topic(d, c)
    -inf: topic(d, 9)

Small words are variables; numbers, quoted strings, ``true`` and ``false`` are constants. ``!`` negates, ``|`` joins
heads, ``!=`` is an inequality.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

TYPES = {"bigint", "int", "string", "double", "date", "timestamp", "timestamp_ntz", "boolean"}


class ProgramError(ValueError):
    """A program that is wrong, with the line it is wrong in."""


@dataclass(frozen=True)
class Predicate:
    name: str
    args: tuple[tuple[str, str], ...]  # domain and type
    open: bool

    @property
    def columns(self) -> list[str]:
        return [f"a{k}" for k in range(1, len(self.args) + 1)]


@dataclass(frozen=True)
class Term:
    value: object
    variable: bool


@dataclass(frozen=True)
class Literal:
    pred: str
    terms: tuple[Term, ...]
    positive: bool

    def variables(self) -> set[str]:
        return {t.value for t in self.terms if t.variable}


@dataclass(frozen=True)
class Equal:
    left: Term
    right: Term
    positive: bool

    def variables(self) -> set[str]:
        return {t.value for t in (self.left, self.right) if t.variable}


@dataclass(frozen=True)
class Clause:
    """Disjunction of literals. ``exists``: variables of head literals that range over all witnesses."""

    id: str
    weight: float
    hard: bool
    literals: tuple[Literal, ...]
    equals: tuple[Equal, ...] = ()
    exists: frozenset[str] = frozenset()


@dataclass
class Program:
    predicates: dict[str, Predicate] = field(default_factory=dict)
    clauses: list[Clause] = field(default_factory=list)

    @staticmethod
    def builder() -> ProgramBuilder:
        return ProgramBuilder()

    @staticmethod
    def parse(text: str) -> Program:
        out = Program()
        for n, line in enumerate(text.splitlines(), 1):
            line = _uncomment(line).strip()
            if not line:
                continue
            try:
                if line.startswith("@"):
                    p = _declaration(line)
                    if p.name in out.predicates:
                        raise ProgramError(f"{p.name} is declared twice")
                    out.predicates[p.name] = p
                else:
                    c = _rule(line, f"r{len(out.clauses) + 1}")
                    out.check(c)
                    out.clauses.append(c)
            except ProgramError as e:
                raise ProgramError(f"line {n}: {e}") from None
        return out

    def check(self, c: Clause) -> None:
        bound: set[str] = set()
        for x in c.literals:
            if x.pred not in self.predicates:
                raise ProgramError(f"{x.pred} is not declared")
            p = self.predicates[x.pred]
            if len(x.terms) != len(p.args):
                raise ProgramError(f"{x.pred} takes {len(p.args)} arguments, not {len(x.terms)}")
            for t, (_, kind) in zip(x.terms, p.args, strict=True):
                if t.variable and kind == "double":
                    raise ProgramError(f"{x.pred}: variables cannot join on a double")
                if not t.variable and not _fits(t.value, kind):
                    raise ProgramError(f"{t.value!r} is no {kind}")
            if (p.open or not x.positive) and not x.variables() & c.exists:
                bound |= x.variables()
            if c.weight < 0 and not p.open and not x.positive:
                raise ProgramError("a rule of negative weight cannot have closed predicates in its body: every absent row would cost")
        needed = set().union(*(x.variables() for x in (*c.literals, *c.equals))) - c.exists
        if needed - bound:
            raise ProgramError(f"unsafe variables {sorted(needed - bound)}: nothing in the rule lists their values")
        if c.exists and (c.weight < 0 or any(x.variables() & c.exists and not x.positive for x in c.literals)):
            raise ProgramError("witnesses may stand in the head of rules of positive weight only")


class ProgramBuilder:
    """A program step by step: ``Program.builder().open("on", n="bigint").rule(1.5, "on(x)", body="e(x, y)").build()``."""

    def __init__(self):
        self.lines: list[str] = []

    def _declare(self, kind: str, name: str, args: dict[str, str] | list[tuple[str, str]]) -> ProgramBuilder:
        pairs = args.items() if isinstance(args, dict) else args
        self.lines.append(f"@{kind} {name}({', '.join(f'{d} {t}' for d, t in pairs)})")
        return self

    def closed(self, name: str, *args: tuple[str, str], **more: str) -> ProgramBuilder:
        """A relation whose absent rows are false; arguments as ``(domain, type)`` pairs or by keyword."""
        return self._declare("closed", name, [*args, *more.items()])

    def open(self, name: str, *args: tuple[str, str], **more: str) -> ProgramBuilder:
        """A relation of atoms with a truth that may be unknown."""
        return self._declare("open", name, [*args, *more.items()])

    def rule(self, weight: float | str, head: str, body: str = "") -> ProgramBuilder:
        """``weight``: a number, ``"hard"`` or ``"-inf"``."""
        self.lines.append(f"{weight}: {body + ' => ' if body else ''}{head}")
        return self

    def build(self) -> Program:
        return Program.parse("\n".join(self.lines))


def _uncomment(line: str) -> str:
    return re.sub(r"^((?:[^#'\"]|'[^']*'|\"[^\"]*\")*)#.*$", r"\1", line)


def _fits(value, kind: str) -> bool:
    if kind in ("bigint", "int"):
        return isinstance(value, int) and not isinstance(value, bool)
    return {"double": isinstance(value, (int, float)), "boolean": isinstance(value, bool)}.get(kind, isinstance(value, str))


def _declaration(line: str) -> Predicate:
    m = re.fullmatch(r"@(open|closed)\s+(\w+)\s*\(([^)]*)\)", line)
    if not m:
        raise ProgramError("a declaration reads '@open name(domain type, ...)'")
    args = []
    for part in filter(None, (x.strip() for x in m[3].split(","))):
        domain, _, kind = part.partition(" ")
        if kind.strip() not in TYPES:
            raise ProgramError(f"unknown type {kind.strip()!r}")
        args.append((domain, kind.strip()))
    return Predicate(m[2], tuple(args), m[1] == "open")


def _term(text: str) -> Term:
    text = text.strip()
    if re.fullmatch(r"'[^']*'|\"[^\"]*\"", text):
        return Term(text[1:-1], False)
    if re.fullmatch(r"-?\d+", text):
        return Term(int(text), False)
    if re.fullmatch(r"-?\d*\.\d+", text):
        return Term(float(text), False)
    if text in ("true", "false"):
        return Term(text == "true", False)
    if not re.fullmatch(r"[a-z]\w*", text):
        raise ProgramError(f"{text!r} is no term")
    return Term(text, True)


def _parts(text: str, mark: str) -> list[str]:
    """Split at a mark outside of quotes and brackets."""
    return [x.strip() for x in re.split(re.escape(mark) + r"(?=(?:[^'\"()]|'[^']*'|\"[^\"]*\"|\((?:[^'\")]|'[^']*'|\"[^\"]*\")*\))*$)", text)]


def _literal(text: str):
    m = re.fullmatch(r"(!?)\s*(\w+)\s*\((.*)\)", text)
    if m:
        return Literal(m[2], tuple(_term(t) for t in _parts(m[3], ",")), not m[1])
    m = re.fullmatch(r"(.+?)\s*(!?=)\s*(.+)", text)
    if not m:
        raise ProgramError(f"{text!r} is no literal")
    return Equal(_term(m[1]), _term(m[3]), m[2] == "=")


def _negated(x):
    return Literal(x.pred, x.terms, not x.positive) if isinstance(x, Literal) else Equal(x.left, x.right, not x.positive)


def to_clause(name: str, weight: float, hard: bool, body: list, head: list, exists: frozenset[str] = frozenset()) -> Clause:
    """An implication as a disjunction: body literals negated, head literals as they are."""
    every = [_negated(x) for x in body] + head
    return Clause(name, weight, hard, tuple(x for x in every if isinstance(x, Literal)), tuple(x for x in every if isinstance(x, Equal)), exists)


def _rule(line: str, name: str) -> Clause:
    m = re.match(r"(hard|[-+]?inf|-?\d+(?:\.\d+)?)\s*:\s*(.+)$", line)
    if not m:
        raise ProgramError("a rule reads 'weight: body => head'")
    hard = m[1] in ("hard", "inf", "+inf", "-inf")
    weight = (-1.0 if m[1] == "-inf" else 1.0) if hard else float(m[1])
    body, arrow, head = (x.strip() for x in m[2].partition("=>"))
    if not arrow:
        body, head = "", body
    exists = re.match(r"exists\s+([\w\s,]+?)\s*:\s*(.+)$", head)
    names = frozenset(x.strip() for x in exists[1].split(",")) if exists else frozenset()
    heads = [_literal(x) for x in _parts(exists[2] if exists else head, "|")]
    return to_clause(name, weight, hard, [_literal(x) for x in _parts(body, "&")] if body else [], heads, names)
