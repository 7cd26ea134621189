"""Queries as DataFrame plans over any scan of triple patterns."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from loadshard.query.ast import Filter, GraphPattern, Query, Term, TriplePattern, Var

Scan = Callable[[TriplePattern], DataFrame]


def matches(t: TriplePattern) -> Column:
    """Row condition of a pattern's constants and repeated variables."""
    out = F.lit(True)
    for c, x in t.parts():
        if isinstance(x, Term):
            out &= F.col(c) == x.text
            if c == "o":
                out &= F.col("o_kind") == x.kind
    at: dict[str, str] = {}
    for c, x in t.parts():
        if isinstance(x, Var):
            if x.name in at:
                out &= F.col(c) == F.col(at[x.name])
                if c == "o":
                    out &= F.col("o_kind") == "iri"
            at.setdefault(x.name, c)
    return out


class Scope:
    """What a graph pattern needs to know of its variables: which stand for IRIs only, which carry a kind or number."""

    def __init__(self, g: GraphPattern, extra: set[str] = frozenset()):
        every = [*g.required, *(t for o in g.optional for t in o)]
        seats: dict[str, list[str]] = {}
        for t in every:
            for c, x in t.parts():
                if isinstance(x, Var):
                    seats.setdefault(x.name, []).append(c)
        told = {v for f in g.filters for v in f.variables} | set(extra)
        self.iri = {v for v, c in seats.items() if set(c) != {"o"}}
        self.kinds = {v for v, c in seats.items() if v not in self.iri and (len(c) > 1 or v in told)}
        self.numbers = {v for v in told if v in seats and v not in self.iri}
        self.narrow: Callable[[TriplePattern], Column] | None = None

    def bind(self, rows: DataFrame, t: TriplePattern, keep: tuple[str, ...] = ()) -> DataFrame:
        """Bindings of one pattern from rows of triples; ``keep`` are further columns to carry."""
        cols, seen = [F.col(c) for c in keep], set()
        for c, x in t.parts():
            if not isinstance(x, Var):
                continue
            if x.name in seen:
                continue
            seen.add(x.name)
            cols.append(F.col(c).alias(x.name))
            if c == "o" and x.name in self.kinds:
                cols.append(F.col("o_kind").alias(f"{x.name}__k"))
            if c == "o" and x.name in self.numbers:
                cols.append(F.col("o_num").alias(f"{x.name}__n"))
        return rows.where(self.asked(t)).select(*cols)

    def asked(self, t: TriplePattern) -> Column:
        """The rows that ``bind`` takes for a pattern."""
        need = matches(t)
        if isinstance(t.o, Var) and t.o.name in self.iri:
            need &= F.col("o_kind") == "iri"
        return need & self.narrow(t) if self.narrow else need


def natural(a: DataFrame, b: DataFrame, how: str = "inner", loose: set[str] = frozenset(), hint: str | None = None) -> DataFrame:
    """Join on shared variables and their kinds. ``loose`` ones may be unbound, and then fit anything."""
    shared = [c for c in a.columns if c in b.columns and not c.endswith("__n")]
    b = b.hint(hint) if hint else b
    b = b.drop(*[c for c in b.columns if c in a.columns and c.endswith("__n")])
    if not shared:
        return a.join(b, how="cross") if how == "inner" else a.join(b, F.lit(True), how)
    if not any(c.removesuffix("__k") in loose for c in shared):
        return a.join(b, shared, how)
    other = b.select(*[F.col(c).alias(f"{c}__r") if c in shared else F.col(c) for c in b.columns])
    fits = reduce(Column.__and__, [((F.col(c) == F.col(f"{c}__r")) | F.col(c).isNull() | F.col(f"{c}__r").isNull()) if c.removesuffix("__k") in loose else F.col(c) == F.col(f"{c}__r") for c in shared])
    out = a.join(other, fits, how)
    return out.select(*[F.coalesce(c, f"{c}__r").alias(c) if c in shared else F.col(c) for c in out.columns if not c.endswith("__r")])


#: Answers that one task makes of a join of many rows with many.
TASK_ROWS = 4_000_000


def multiplies(a: Iterable[TriplePattern], b: Iterable[TriplePattern]) -> bool:
    """Whether each variable that two sides of a join share is an object on both, so that many rows may meet many."""
    names = [{x.name for t in side for x in (t.s, t.p, t.o) if isinstance(x, Var)} for side in (a, b)]
    objects = [{t.o.name for t in side if isinstance(t.o, Var)} for side in (a, b)]
    shared = names[0] & names[1]
    return bool(shared) and shared <= objects[0] & objects[1]


def spread(a: DataFrame, b: DataFrame, of_a: Iterable[TriplePattern], of_b: Iterable[TriplePattern], hint: str | None = None) -> DataFrame:
    """``natural`` of rows that answer the given patterns. Where many rows meet many, the work is dealt to tasks by the rows
    that the join gives, not by those it reads: a key's rows of the larger side are dealt to shares, and those of the other
    side are repeated for each share. Only counts by key are looked at before."""
    if not multiplies(of_a, of_b):
        return natural(a, b, hint=hint)
    keys = [c for c in a.columns if c in b.columns and not c.endswith("__n")]
    counted = lambda d, name: d.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias(name))
    met = F.col("left__") * F.col("right__")
    total, most, left, right = counted(a, "left__").join(counted(b, "right__"), keys).agg(F.sum(met), F.max(met), F.sum("left__"), F.sum("right__")).first()
    if (total or 0) <= TASK_ROWS:
        return natural(a, b, hint=hint)
    a, b = (a, b) if left >= right else (b, a)
    shares, tasks = math.ceil(2 * most / TASK_ROWS), math.ceil(total / TASK_ROWS)
    a = a.withColumn("share__", F.pmod(F.xxhash64(*a.columns), F.lit(shares)).cast("int")).repartition(tasks, *keys, "share__")
    b = b.withColumn("share__", F.explode(F.sequence(F.lit(0), F.lit(shares - 1)))).repartition(tasks, *keys, "share__")
    return natural(a, b, hint="shuffle_hash").drop("share__")


def condition(f: Filter, columns: list[str]) -> Column:
    """A filter over bindings. Comparisons with numbers need numeric literals; an error or unbound value is false."""
    if f.op in ("&&", "||"):
        a, b = (condition(x, columns) for x in f.args)
        return a & b if f.op == "&&" else a | b
    if f.op == "!":
        return ~F.coalesce(condition(f.args[0], columns), F.lit(True))
    v = f.args[0]
    text = lambda x: F.col(x.name) if isinstance(x, Var) else F.lit(x.text)
    if isinstance(v, Var) and v.name not in columns:
        return F.lit(False)
    if f.op == "bound":
        return F.col(v.name).isNotNull()
    if f.op in ("isIRI", "isLiteral", "isNumeric"):
        k = F.col(f"{v.name}__k") if f"{v.name}__k" in columns else F.lit("iri")
        return {"isIRI": k == "iri", "isLiteral": k != "iri", "isNumeric": k == "num"}[f.op]
    if f.op == "regex":
        return text(v).rlike(f.args[1].text)
    if f.op == "contains":
        return text(v).contains(text(f.args[1]))
    if f.op == "strstarts":
        return text(v).startswith(text(f.args[1]))
    a, b = f.args
    numeric = any(isinstance(x, Term) and x.kind in ("num", "ts") for x in (a, b))
    number = lambda x: F.lit(x.number) if isinstance(x, Term) else (F.col(f"{x.name}__n") if f"{x.name}__n" in columns else F.lit(None).cast("double"))
    x, y = (number(a), number(b)) if numeric else (text(a), text(b))
    out = {"<": x < y, "<=": x <= y, "=": x == y, ">=": x >= y, ">": x > y, "!=": x != y}[f.op]
    if numeric:
        kinds = [F.col(f"{z.name}__k").isin("num", "ts") for z in (a, b) if isinstance(z, Var) and f"{z.name}__k" in columns]
        out = reduce(Column.__and__, kinds, out)
    return out


def join_order(patterns: tuple[TriplePattern, ...]) -> list[TriplePattern]:
    """Connected order, patterns with more constants first, then those that don't multiply the rows so far; used where no
    statistics are at hand."""
    left, out, known = list(patterns), [], set()
    weight = lambda t: -sum(isinstance(x, Term) for _, x in t.parts())
    while left:
        pick = min(left, key=lambda t: (bool(out) and not known & set(t.variables), weight(t), multiplies(out, [t])))
        left.remove(pick)
        out.append(pick)
        known |= set(pick.variables)
    return out


def finish_pattern(g: GraphPattern, rows: DataFrame, scope: Scope, scan: Scan, early: bool = True) -> DataFrame:
    """Optional parts and filters over the joined required patterns."""
    sure = {v for t in g.required for v in t.variables}
    rest = list(g.filters)
    if early:
        for f in [f for f in rest if f.variables <= sure]:
            rows = rows.where(condition(f, rows.columns))
            rest.remove(f)
    for part in g.optional:
        inner = reduce(natural, [scope.bind(scan(t), t) for t in join_order(part)])
        loose = (set(rows.columns) & set(inner.columns)) - sure
        rows = natural(rows, inner, "left", {c for c in loose if "__" not in c})
    for f in rest:
        rows = rows.where(condition(f, rows.columns))
    return rows


def finish_query(q: Query, branches: list[DataFrame]) -> DataFrame:
    """Union, projection and solution modifiers."""
    out = q.output
    if q.form == "count":
        rows = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), [b.select(*[c for c in out if c in b.columns]) for b in branches])
        return rows.agg(F.count(F.lit(1)).alias("n"))
    keys = [o for o, _ in q.order]
    parts = []
    for b in branches:
        cols = [F.col(c) if c in b.columns else F.lit(None).cast("string").alias(c) for c in out]
        cols += [F.col(f"{k}__n").alias(f"{k}__n") for k in keys if f"{k}__n" in b.columns]
        parts.append(b.select(*cols))
    rows = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)
    if q.form == "ask":
        return rows.limit(1).agg((F.count(F.lit(1)) > 0).alias("answer"))
    if q.distinct:
        rows = rows.select(*out).distinct()
    if q.order:
        rows = rows.orderBy(*[x for k, up in q.order for x in ([F.col(f"{k}__n").asc() if up else F.col(f"{k}__n").desc()] if f"{k}__n" in rows.columns else []) + [F.col(k).asc() if up else F.col(k).desc()]])
    if q.offset:
        rows = rows.offset(q.offset)
    if q.limit is not None:
        rows = rows.limit(q.limit)
    return rows.select(*out)


def to_dataframe(q: Query, triples: DataFrame) -> DataFrame:
    """Central execution: self joins over one relation, in which Catalyst picks joins and pushes filters."""
    done = []
    for g in q.branches:
        scope = Scope(g, {k for k, _ in q.order})
        scan = lambda t: triples
        order = join_order(g.required)
        rows = scope.bind(triples, order[0])
        for i, t in enumerate(order[1:], 1):
            rows = spread(rows, scope.bind(triples, t), order[:i], [t])
        done.append(finish_pattern(g, rows, scope, scan))
    return finish_query(q, done)
