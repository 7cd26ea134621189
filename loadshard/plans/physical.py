"""Plans as DataFrames, with exchanges marked and, on request, counted."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from loadshard.operators.store import Store
from loadshard.plans.cost import PAGE, CostParams, moved_pages, pages, plan_cost
from loadshard.plans.initial import optimize
from loadshard.plans.ir import Node, scans
from loadshard.plans.placing import assign, distribute_joins, expand_leaves, parts_of, relevant
from loadshard.query.ast import GraphPattern, Query, TriplePattern
from loadshard.query.compile import Scope, finish_pattern, finish_query, natural, spread


@dataclass
class Planned:
    """A graph pattern's plan."""

    pattern: GraphPattern
    root: Node
    cost: float

    @property
    def sites(self) -> set[int]:
        return {s for x in scans(self.root) for s in x.sites}

    @property
    def fragments(self) -> set[int]:
        return {f for x in scans(self.root) for f in x.frags}


def plan(q: Query, store: Store, c: CostParams | None = None, prune: bool = True, distribute: bool = True) -> list[Planned]:
    """A plan for each branch of a query: join order, sites, homes, distributed joins."""
    c = c or CostParams()
    out = []
    for g in q.branches:
        tree = expand_leaves(optimize(g.required, store.stats, q, c), q, store, prune)
        root = distribute_joins(tree, store, c) if distribute else assign(tree, store.placement.n, c)
        out.append(Planned(g, root, plan_cost(root, c)))
    return out


@dataclass
class Meter:
    """Rows that exchanges move; filled once an action has run."""

    seen: list[tuple[str, Observation]] = field(default_factory=list)

    def watch(self, df: DataFrame, label: str) -> DataFrame:
        o = Observation()
        self.seen.append((label, o))
        return df.observe(o, F.count(F.lit(1)).alias("rows"))

    def rows(self) -> list[tuple[str, int]]:
        return [(label, o.get["rows"]) for label, o in self.seen]

    def pages(self) -> int:
        return sum(-(-n // PAGE) for _, n in self.rows())


def read(n: Node, store: Store, scope: Scope) -> DataFrame:
    """A scan of some sites' fragments: both are partition columns, so only their files are opened."""
    return scope.bind(store.triples.where(F.col("site_id").isin(list(n.sites)) & F.col("frag_id").isin(list(n.frags))), n.pattern)


def leaves(n: Node) -> list[tuple[TriplePattern, tuple[int, ...], tuple[int, ...]]] | None:
    """(pattern, fragments, sites) of the scans below joins; None where a union is of more than scans of one pattern."""
    if n.kind == "scan":
        return [(n.pattern, n.frags, n.sites)]
    if n.kind == "union":
        parts = parts_of(n)
        if any(p.kind != "scan" or p.pattern != parts[0].pattern for p in parts):
            return None
        return [(parts[0].pattern, tuple(sorted({f for p in parts for f in p.frags})), tuple(sorted({s for p in parts for s in p.sites})))]
    below = [leaves(k) for k in n.children]
    return None if any(b is None for b in below) else [x for b in below for x in b]


def starred(n: Node, store: Store, scope: Scope) -> DataFrame | None:
    """Joins below a node with each star that the store answers by one scan; None where there is no such star. Stars are
    joined in the plan's order of their first patterns, those that share a variable first."""
    groups: dict[object, list] = {}
    for x in leaves(n) or ():
        groups.setdefault(x[0].s, []).append(x)
    found = {s: store.star(g, scope) for s, g in groups.items() if len(g) > 1}
    if not any(x is not None for x in found.values()):
        return None
    left = []
    for s, g in groups.items():
        one = found.get(s)
        left += [(one, [t for t, *_ in g])] if one is not None else [(read(Node("scan", 0, t.variables, pattern=t, frags=frags, sites=sites), store, scope), [t]) for t, frags, sites in g]
    rows, of = left.pop(0)
    while left:
        at = next((i for i, (x, _) in enumerate(left) if set(x.columns) & set(rows.columns)), 0)
        more, patterns = left.pop(at)
        rows, of = spread(rows, more, of, patterns), [*of, *patterns]
    return rows


def build(n: Node, store: Store, scope: Scope, meter: Meter | None, home: int | None) -> DataFrame:
    here = home if n.kind == "union" else n.home
    if n.kind == "scan":
        return read(n, store, scope)
    if n.kind == "union":
        parts = parts_of(n)
        if all(p.kind == "scan" and p.pattern == parts[0].pattern for p in parts) and meter is None:
            # scans of one pattern at several sites are one scan: a union would lose its partitioning
            return read(Node("scan", n.rows, n.vars, pattern=parts[0].pattern, frags=tuple(sorted({f for p in parts for f in p.frags})), sites=tuple(sorted({s for p in parts for s in p.sites}))), store, scope)
        return reduce(lambda a, b: a.unionByName(b), [shipped(p, store, scope, meter, here) for p in parts])
    if n.kind == "join" and store.star and meter is None and (rows := starred(n, store, scope)) is not None:
        return rows
    if n.kind == "sort":
        return build(n.children[0], store, scope, meter, here)  # Spark sorts where its join asks for it
    sides = [shipped(k, store, scope, meter, here) for k in n.children]
    if store.star is None or meter is not None:
        return natural(*sides)
    return spread(*sides, *([x.pattern for x in scans(k)] for k in n.children))


def shipped(n: Node, store: Store, scope: Scope, meter: Meter | None, home: int | None) -> DataFrame:
    df = build(n, store, scope, meter, home)
    moved = n.kind != "union" and n.home != home
    return meter.watch(df, f"{n.home}>{home}") if meter is not None and moved else df


def execute(q: Query, store: Store, c: CostParams | None = None, prune: bool = True, meter: Meter | None = None) -> DataFrame:
    """The query's answer over the placed triples, as a plan that Spark runs when asked."""
    done = []
    whole = store.star is not None and meter is None  # stars are found in joins that are not dealt to sites
    for p in plan(q, store, c, prune, distribute=not whole):
        scope = Scope(p.pattern, {k for k, _ in q.order})
        scope.narrow = store.narrow(p.pattern) if store.narrow else None
        rows = build(p.root, store, scope, meter, p.root.home)

        def scan(t):
            where = relevant(t, q, store, prune)
            return store.triples.where(F.col("site_id").isin(list(where)) & F.col("frag_id").isin(sorted({f for fs in where.values() for f in fs})))

        done.append(finish_pattern(p.pattern, rows, scope, scan))
    return finish_query(q, done)


def subqueries(root: Node) -> list[tuple[int | None, list[str]]]:
    """(home, operators) of the largest same-home subtrees, which are shipped as one."""
    out = []

    def visit(n: Node, home: int | None, ops: list[str]) -> None:
        ops.append(label(n))
        for k in n.children:
            at = home if k.kind == "union" else k.home
            if at == home:
                visit(k, home, ops)
            else:
                out.append((at, inner := []))
                visit(k, at, inner)

    out.append((root.home, top := []))
    visit(root, root.home, top)
    return out


def label(n: Node) -> str:
    if n.kind == "scan":
        return f"scan[{n.method}] " + " ".join(x.text if hasattr(x, "text") else f"?{x.name}" for _, x in n.pattern.parts()) + f" fragments {list(n.frags)}"
    return f"{n.method + ' ' if n.method else ''}{n.kind}" + (f" on {','.join(n.on)}" if n.on else "")


def render(root: Node, c: CostParams | None = None) -> str:
    """Text of a plan with homes, expected rows and pages, and exchanges where homes differ."""
    lines = [f"cost {plan_cost(root, c or CostParams()):.2f}, pages moved {moved_pages(root)}"]

    def visit(n: Node, home: int | None, depth: int) -> None:
        here = home if n.kind == "union" else n.home
        if here != home:
            lines.append("  " * depth + f"exchange site {here} -> site {home}, {pages(n.rows)} pages")
            depth += 1
        lines.append("  " * depth + f"{label(n)} @ site {here}, {n.rows:.0f} rows")
        for k in n.children:
            visit(k, here, depth + 1)

    visit(root, root.home, 1)
    return "\n".join(lines)
