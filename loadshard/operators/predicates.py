"""Simple predicates over one triple component, their satisfiable combinations, and cell codes of triples.

For each component the equality constants, the intervals between range bounds and the truths of functions give a small
code; a triple's three codes name its cell. A cell fixes the truth of every predicate, so all fragmentations by
subsets of the predicates are unions of cells, and one count of triples by cell serves them all."""

from __future__ import annotations

import itertools
import re
from bisect import bisect_left, bisect_right
from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from loadshard.query.ast import Query, Term
from loadshard.workload.load import Analysis, filters_of

RANGE = ("<", "<=", ">=", ">")
FUNCTIONS = ("isIRI", "isLiteral", "isNumeric", "regex", "contains", "strstarts")


@dataclass(frozen=True, order=True)
class Predicate:
    """component op value; ops are comparisons with a constant, or boolean functions (value: their argument)."""

    component: str
    op: str
    value: str
    kind: str = "iri"

    @property
    def number(self) -> float:
        return float(self.value)

    def __str__(self) -> str:
        return f"{self.component} {self.op} {self.value}"

    def holds(self, text: str, kind: str, number: float | None) -> bool:
        """Truth for one term."""
        if self.op == "=":
            return text == self.value and (self.component != "o" or kind == self.kind)
        if self.op in RANGE:
            if number is None or kind != self.kind:
                return False
            v = self.number
            return {"<": number < v, "<=": number <= v, ">=": number >= v, ">": number > v}[self.op]
        return {
            "isIRI": lambda: kind == "iri", "isLiteral": lambda: kind != "iri", "isNumeric": lambda: kind == "num", "regex": lambda: re.search(self.value, text) is not None,
            "contains": lambda: self.value in text, "strstarts": lambda: text.startswith(self.value),
        }[self.op]()

    def column(self) -> Column:
        """Truth for rows of triples; never null."""
        c = F.col(self.component)
        kind = F.col("o_kind") if self.component == "o" else F.lit("iri")
        if self.op == "=":
            return (c == self.value) & ((kind == self.kind) if self.component == "o" else F.lit(True))
        if self.op in RANGE:
            n, v = F.col("o_num"), F.lit(self.number)
            return F.coalesce({"<": n < v, "<=": n <= v, ">=": n >= v, ">": n > v}[self.op] & (kind == self.kind), F.lit(False))
        return {"isIRI": kind == "iri", "isLiteral": kind != "iri", "isNumeric": kind == "num", "regex": c.rlike(self.value), "contains": c.contains(self.value), "strstarts": c.startswith(self.value)}[self.op]


def extract(a: Analysis) -> list[Predicate]:
    """Predicates of the patterns' constants and of the queries' filters, in a fixed order."""
    out = {Predicate(c, "=", v, k) for p in a.patterns.values() for c, v, k in p.constants()}
    for q in a.queries:
        out |= set(from_filters(q))
    return sorted(out)


def from_filters(q: Query) -> list[Predicate]:
    """A filter on a variable constrains each component where the variable stands; comparisons of two components
    and of two variables give none."""
    found = []
    for g in q.branches:
        for t in [*g.required, *(t for part in g.optional for t in part)]:
            for c, op, v in filters_of(q, t):
                if op in RANGE and (c != "o" or v.kind not in ("num", "ts")):
                    continue
                found.append(Predicate(c, op, v.text, v.kind))
    return found


# satisfiability -------------------------------------------------------------------------------------


def component_satisfiable(signs: list[tuple[Predicate, bool]]) -> bool:
    """Whether some term gives these predicates of one component these truths.

    Sound and, but for opaque functions (regex, contains, strstarts) without an equality, complete: constants are
    tried, intervals are intersected per kind, kinds are told by functions."""
    equal = [p for p, yes in signs if p.op == "=" and yes]
    if equal:
        v = equal[0]
        kind = v.kind if v.component == "o" else "iri"
        number = float(v.value) if kind in ("num", "ts") else None
        return all(p.holds(v.value, kind, number) == yes for p, yes in signs)
    subject = signs and signs[0][0].component != "o"
    for kind in ("iri",) if subject else ("iri", "str", "num", "ts"):
        if any({"isIRI": kind == "iri", "isLiteral": kind != "iri", "isNumeric": kind == "num"}[p.op] != yes for p, yes in signs if p.op in ("isIRI", "isLiteral", "isNumeric")):
            continue
        ranged = [(p, yes) for p, yes in signs if p.op in RANGE]
        if any(p.kind != kind and yes for p, yes in ranged):
            continue
        ranged = [(p, yes) for p, yes in ranged if p.kind == kind]
        if ranged:
            bounds = sorted({p.number for p, _ in ranged})
            tries = {x for b in bounds for x in (b, b - 1, b + 1)} | {(x + y) / 2 for x, y in itertools.pairwise(bounds)}
            taken = {float(p.value) for p, yes in signs if p.op == "=" and not yes and p.kind == kind}
            open_side = lambda x: x in bounds and x in taken
            if not any(not open_side(x) and all(p.holds("", kind, x) == yes for p, yes in ranged) for x in tries):
                continue
        return True
    return not signs


def satisfiable(signs: list[tuple[Predicate, bool]]) -> bool:
    return all(component_satisfiable(part) for c in "spo" if (part := [(p, y) for p, y in signs if p.component == c]))


def enumerate_all(s: list[Predicate]) -> list[tuple[bool, ...]]:
    """Every sign vector, 2^|S| of them; the small-S oracle."""
    if len(s) > 16:
        raise ValueError("at most 16 predicates here")
    return list(itertools.product((True, False), repeat=len(s)))


def satisfiable_minterms(s: list[Predicate]) -> list[tuple[bool, ...]]:
    """Satisfiable sign vectors as the product of the components' own, without enumerating 2^|S|."""
    per = []
    for c in "spo":
        of = [i for i, p in enumerate(s) if p.component == c]
        eq = [i for i in of if s[i].op == "="]
        rest = [i for i in of if s[i].op != "="]
        choices = []
        for chosen in [None, *eq]:
            for signs in itertools.product((True, False), repeat=len(rest)):
                row = {i: i == chosen for i in eq} | dict(zip(rest, signs, strict=True))
                if not of or component_satisfiable([(s[i], row[i]) for i in of]):
                    choices.append(row)
        per.append(choices or [{}])
    out = []
    for rows in itertools.product(*per):
        merged = {k: v for r in rows for k, v in r.items()}
        out.append(tuple(merged[i] for i in range(len(s))))
    return out


# cells ----------------------------------------------------------------------------------------------


class Cells:
    """Cell codes of a predicate list. Codes are small numbers; their cost for a row is three map lookups and an
    interval search, whatever the number of predicates."""

    def __init__(self, predicates: list[Predicate]):
        self.predicates = list(predicates)
        self.equal = {c: [p for p in predicates if p.component == c and p.op == "="] for c in "spo"}
        self.functions = {c: [p for p in predicates if p.component == c and p.op in FUNCTIONS] for c in "spo"}
        self.bounds = {k: sorted({p.number for p in predicates if p.op in RANGE and p.kind == k}) for k in ("num", "ts")}

    @cached_property
    def _eq_code(self) -> dict:
        return {c: {(p.value, p.kind if c == "o" else "iri"): i + 1 for i, p in enumerate(ps)} for c, ps in self.equal.items()}

    def code(self, c: str, text: str, kind: str, number: float | None) -> tuple[int, int, int]:
        """(constant, interval, functions) of a term, on the driver."""
        e = self._eq_code[c].get((text, kind if c == "o" else "iri"), 0)
        r = 0
        if c == "o" and number is not None and (b := self.bounds.get(kind)):
            r = 1 + bisect_left(b, number) + bisect_right(b, number)
            r = r + (2 * len(self.bounds["num"]) + 1) * (kind == "ts")
        f = sum(1 << i for i, p in enumerate(self.functions[c]) if p.holds(text, kind, number))
        return e, r, f

    def columns(self, may: Callable[[str, str, str], bool] | None = None) -> dict[str, Column]:
        """s_cell, p_cell, o_cell as struct-free strings "constant.interval.functions". Constants (component, value, kind)
        that ``may`` denies are not looked for."""
        out = {}
        for c in "spo":
            value = F.concat_ws("\x01", "o_kind", "o") if c == "o" else F.col(c)
            known = {x: i for x, i in self._eq_code[c].items() if may is None or may(c, *x)}
            if known:
                pairs = [x for (v, k), i in known.items() for x in (F.lit(f"{k}\x01{v}" if c == "o" else v), F.lit(i))]
                e = F.coalesce(F.try_element_at(F.create_map(*pairs), value), F.lit(0))
            else:
                e = F.lit(0)
            r = F.lit(0)
            if c == "o":
                base = 0
                for kind in ("num", "ts"):
                    if b := self.bounds[kind]:
                        steps = F.lit(1 + base)
                        for x in b:
                            steps = steps + (F.col("o_num") > x).cast("int") + (F.col("o_num") >= x).cast("int")
                        r = F.when((F.col("o_kind") == kind) & F.col("o_num").isNotNull(), steps).otherwise(r)
                    base += 2 * len(b) + 1 if kind == "num" else 0
            f = F.lit(0)
            for i, p in enumerate(self.functions[c]):
                f = f + F.coalesce(p.column(), F.lit(False)).cast("int") * F.lit(1 << i)
            out[f"{c}_cell"] = F.concat_ws(".", e.cast("string"), r.cast("string"), f.cast("string"))
        return out

    def truths(self, cell: tuple[str, str, str]) -> int:
        """Bits of the predicates that hold in a cell."""
        bits = 0
        for c, code in zip("spo", cell, strict=True):
            e, r, f = map(int, code.split("."))
            for i, p in enumerate(self.predicates):
                if p.component != c:
                    continue
                if p.op == "=":
                    yes = e > 0 and self.equal[c][e - 1] == p
                elif p.op in RANGE:
                    yes = self._in_interval(p, r)
                else:
                    yes = bool(f >> self.functions[c].index(p) & 1)
                bits |= yes << i
        return bits

    def _in_interval(self, p: Predicate, r: int) -> bool:
        base = 2 * len(self.bounds["num"]) + 1 if p.kind == "ts" else 0
        at = r - 1 - base
        b = self.bounds[p.kind]
        if r == 0 or not 0 <= at <= 2 * len(b) or p.kind == "num" and r > 2 * len(b) + 1:
            return False
        mine = 2 * b.index(p.number) + 1  # odd places are the bounds, even ones the gaps between
        return {"<": at < mine, "<=": at <= mine, ">=": at >= mine, ">": at > mine}[p.op]


def histogram(triples: DataFrame, cells: Cells, fraction: float | None = None) -> list[tuple[tuple[str, str, str], int]]:
    """(cell, triples) of the cells that occur: one scan, partial counts; the result has a row for each cell.

    ``fraction`` counts a sample chosen by a hash of the subject and scales it up."""
    if fraction is not None:
        step = max(1, round(1 / fraction))
        triples = triples.where(F.pmod(F.xxhash64("s"), F.lit(step)) == 0)
    got = triples.select(*[v.alias(k) for k, v in cells.columns().items()]).groupBy("s_cell", "p_cell", "o_cell").count().collect()
    scale = 1 if fraction is None else max(1, round(1 / fraction))
    return sorted(((r[0], r[1], r[2]), r[3] * scale) for r in got)


def exclusive(term: Term | None, p: Predicate) -> bool:
    """Whether a constant makes a predicate of its component false."""
    return term is not None and not p.holds(term.text, term.kind, term.number)
