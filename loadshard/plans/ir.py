"""Operator trees of the planner: what runs where, before it becomes a DataFrame."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from loadshard.query.ast import TriplePattern


@dataclass(frozen=True)
class Node:
    """kind: scan, union, join or sort. A union takes its consumer's home."""

    kind: str
    rows: float
    vars: tuple[str, ...]
    order: str | None = None
    children: tuple[Node, ...] = ()
    home: int | None = None
    pattern: TriplePattern | None = None
    frags: tuple[int, ...] = ()
    sites: tuple[int, ...] = ()
    method: str = ""  # of a join: merge or hash
    on: tuple[str, ...] = ()
    distinct: tuple[tuple[str, float], ...] = field(default=(), compare=False)
    read: float = 0.0  # of a scan: rows of the fragments it reads

    def at(self, home: int | None) -> Node:
        return replace(self, home=home)

    def walk(self):
        yield self
        for c in self.children:
            yield from c.walk()

    def distinct_of(self, v: str) -> float:
        return dict(self.distinct).get(v, self.rows)


def scans(n: Node) -> list[Node]:
    return [x for x in n.walk() if x.kind == "scan"]


def joins(n: Node) -> list[Node]:
    return [x for x in n.walk() if x.kind == "join"]
