"""The syntax tree of rule programs. Everything here is small and lives on the driver."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Const:
    """A constant; the value None is NULL and only appears as padding that the compiler adds."""

    value: int | float | str | None


@dataclass(frozen=True)
class Wild:
    """A wildcard."""


@dataclass(frozen=True)
class Arith:
    op: str
    left: Term
    right: Term


Term = Var | Const | Wild | Arith


@dataclass(frozen=True)
class Atom:
    pred: str
    args: tuple[Term, ...]
    negated: bool = False


@dataclass(frozen=True)
class Compare:
    op: str
    left: Term
    right: Term


@dataclass(frozen=True)
class Either:
    """A disjunction of bodies; gone after normalization."""

    bodies: tuple[tuple[Literal, ...], ...]


Literal = Atom | Compare | Either


@dataclass(frozen=True)
class Rule:
    """Heads and one body; after normalization one head, whose arguments are distinct variables."""

    heads: tuple[Atom, ...]
    body: tuple[Literal, ...]

    @property
    def head(self) -> Atom:
        return self.heads[0]

    @property
    def atoms(self) -> list[Atom]:
        return [x for x in self.body if isinstance(x, Atom)]

    @property
    def compares(self) -> list[Compare]:
        return [x for x in self.body if isinstance(x, Compare)]


@dataclass
class Program:
    """Declarations (columns with types), inputs, outputs and rules."""

    schema: dict[str, list[tuple[str, str]]] = field(default_factory=dict)
    inputs: list[str] = field(default_factory=list)
    outputs: list[str] = field(default_factory=list)
    rules: list[Rule] = field(default_factory=list)

    @property
    def idb(self) -> list[str]:
        return list(dict.fromkeys(h.pred for r in self.rules for h in r.heads))

    @property
    def edb(self) -> list[str]:
        used = [a.pred for r in self.rules for a in body_atoms(r.body)]
        own = set(self.idb)
        return [p for p in dict.fromkeys([*self.inputs, *used]) if p not in own]


def body_atoms(body: tuple[Literal, ...]) -> Iterator[Atom]:
    for x in body:
        if isinstance(x, Atom):
            yield x
        elif isinstance(x, Either):
            for b in x.bodies:
                yield from body_atoms(b)


def variables(term: Term | Literal) -> Iterator[str]:
    """Names of the variables of a term or literal, in order."""
    if isinstance(term, Var):
        yield term.name
    elif isinstance(term, Arith | Compare):
        yield from variables(term.left)
        yield from variables(term.right)
    elif isinstance(term, Atom):
        for a in term.args:
            yield from variables(a)
    elif isinstance(term, Either):
        for b in term.bodies:
            for x in b:
                yield from variables(x)


def renamed(x, names: dict[str, str]):
    """A term or literal with variables renamed."""
    if isinstance(x, Var):
        return Var(names.get(x.name, x.name))
    if isinstance(x, Arith):
        return Arith(x.op, renamed(x.left, names), renamed(x.right, names))
    if isinstance(x, Compare):
        return Compare(x.op, renamed(x.left, names), renamed(x.right, names))
    if isinstance(x, Atom):
        return Atom(x.pred, tuple(renamed(a, names) for a in x.args), x.negated)
    return x
