"""Queries as small driver-side values: graph patterns of required and optional triple patterns, and filters."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Term:
    """A constant; kind is iri, str, num or ts."""

    text: str
    kind: str = "iri"

    @property
    def number(self) -> float | None:
        return float(self.text) if self.kind in ("num", "ts") else None


@dataclass(frozen=True)
class TriplePattern:
    s: Var | Term
    p: Var | Term
    o: Var | Term

    def parts(self) -> tuple[tuple[str, Var | Term], ...]:
        return ("s", self.s), ("p", self.p), ("o", self.o)

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(x.name for _, x in self.parts() if isinstance(x, Var)))


@dataclass(frozen=True)
class Filter:
    """op: < <= = >= > != && || ! regex contains strstarts isIRI isLiteral isNumeric bound; args: Filter, Var or Term."""

    op: str
    args: tuple

    @property
    def variables(self) -> set[str]:
        return {v for a in self.args for v in (a.variables if isinstance(a, Filter) else {a.name} if isinstance(a, Var) else ())}


@dataclass(frozen=True)
class GraphPattern:
    required: tuple[TriplePattern, ...]
    optional: tuple[tuple[TriplePattern, ...], ...] = ()
    filters: tuple[Filter, ...] = ()

    @property
    def variables(self) -> list[str]:
        every = [*self.required, *(t for o in self.optional for t in o)]
        return list(dict.fromkeys(v for t in every for v in t.variables))


@dataclass(frozen=True)
class Query:
    branches: tuple[GraphPattern, ...]
    select: tuple[str, ...] = ()  # empty: all variables
    distinct: bool = False
    order: tuple[tuple[str, bool], ...] = ()  # name, ascending
    limit: int | None = None
    offset: int = 0
    form: str = "select"  # select, ask or count
    qid: str = field(default="", compare=False)

    @property
    def output(self) -> list[str]:
        return list(self.select) or list(dict.fromkeys(v for b in self.branches for v in b.variables))
