"""Fragmentation: reduced predicate sets, fragments as unions of cells, their frequencies, sizes and loads."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.operators.predicates import Cells, Predicate, extract, histogram
from loadshard.query.ast import Query, Term, TriplePattern
from loadshard.workload.load import Analysis, filters_of

SIGNATURES = ("pattern_set", "access", "load", "none")
MODES = ("pattern_sum", "query_count", "closest")


@dataclass
class Fragment:
    number: int
    bits: int  # truths of the kept predicates
    pos: tuple[Predicate, ...]
    neg: tuple[Predicate, ...]
    size: int
    freq: int = 0
    remainder: bool = False
    cells: list = field(default_factory=list, repr=False)

    @property
    def load(self) -> int:
        return self.freq * self.size

    def label(self) -> str:
        return " & ".join(str(p) for p in self.pos) or "all negated"


def pattern_masks(a: Analysis, predicates: list[Predicate], filter_aware: bool = False) -> list[tuple[str, int, int]]:
    """(pattern, needed bits, weight): the predicates a triple must satisfy to match a pattern's constants. With
    ``filter_aware`` each occurrence counts for itself and needs its own filters too."""
    at = {p: i for i, p in enumerate(predicates)}
    need = lambda cs: sum(1 << at[p] for p in {Predicate(c, "=", v, k) for c, v, k in cs} if p in at)
    if not filter_aware:
        return [(p.key, need(p.constants()), p.freq) for p in a.patterns.values()]
    kept = {(c, v, k) for p in a.patterns.values() for c, v, k in p.constants()}
    out = {}
    for q in a.queries:
        for g in q.branches:
            for t in [*g.required, *(t for part in g.optional for t in part)]:
                cs = [(c, x.text, x.kind) for c, x in t.parts() if isinstance(x, Term) and (c == "p" or (c, x.text, x.kind) in kept)]
                fs = [Predicate(c, op, v.text, v.kind) for c, op, v in filters_of(q, t)]
                bits = need(cs) | sum(1 << at[p] for p in set(fs) if p in at)
                key = f"{sorted(cs)} {sorted(map(str, fs))}"
                out.setdefault(key, [bits, set()])[1].add(q.qid)
    return [(k, bits, sum(a.weights[q] for q in qs)) for k, (bits, qs) in sorted(out.items())]


def reduce_predicates(predicates: list[Predicate], counts: list[tuple[int, int]], a: Analysis, signature: str = "pattern_set", filter_aware: bool = True) -> list[Predicate]:
    """A complete and minimal subset: predicates are added while they split a non-empty fragment whose two parts
    differ under ``signature``, and dropped once they no longer do. counts: (truth bits, triples) of all cells, so no
    candidate needs a scan.

    pattern_set: the parts are met by different patterns; access: by patterns of different total frequency; load: the
    multiset of loads changes; none: every predicate stays."""
    if signature == "none":
        return list(predicates)
    masks = pattern_masks(a, predicates, filter_aware and signature != "load")
    met = {bits: frozenset(k for k, need, _ in masks if bits & need == need) for bits, _ in counts}
    weight = {k: w for k, _, w in masks}
    freq = {p: sum(w for _, need, w in masks if need >> i & 1) for i, p in enumerate(predicates)}
    index = {p: i for i, p in enumerate(predicates)}

    def parts(mask: int) -> dict[int, list]:
        out: dict[int, list] = {}
        for bits, n in counts:
            x = out.setdefault(bits & mask, [0, frozenset()])
            x[0] += n
            x[1] |= met[bits]
        return out

    def told(x: list):
        if signature == "pattern_set":
            return x[1]
        f = sum(weight[k] for k in x[1])
        return f if signature == "access" else f * x[0]

    def matters(mask: int, i: int) -> bool:
        fine = parts(mask | 1 << i)
        if signature == "load":
            loads = lambda d: sorted(v for x in d.values() if (v := told(x)))
            return loads(fine) != loads(parts(mask & ~(1 << i)))
        rest = ~(1 << i)
        pairs: dict[int, list] = {}
        for bits, x in fine.items():
            pairs.setdefault(bits & rest, []).append(x)
        return any(len(p) == 2 and told(p[0]) != told(p[1]) for p in pairs.values())

    chosen: list[Predicate] = []
    order = sorted(predicates, key=lambda p: (-freq[p], str(p)))
    mask = lambda ps: sum(1 << index[p] for p in ps)
    for _ in range(len(predicates) + 1):
        before = list(chosen)
        for p in order:
            if p not in chosen and matters(mask(chosen), index[p]):
                chosen.append(p)
                for old in chosen[:-1]:
                    if not matters(mask(x for x in chosen if x != old), index[old]):
                        chosen.remove(old)
        if chosen == before:
            break
    return sorted(chosen)


@dataclass
class Fragmentation:
    predicates: list[Predicate]
    cells: Cells
    fragments: list[Fragment]
    analysis: Analysis
    of_cell: dict[tuple[str, str, str], int]
    candidates: int = 0
    cell_size: dict[tuple[str, str, str], int] = field(default_factory=dict, repr=False)

    @property
    def remainder(self) -> Fragment | None:
        return next((f for f in self.fragments if f.remainder), None)

    def overlaps(self, f: Fragment, need: int) -> bool:
        return f.bits & need == need

    def assign(self, triples: DataFrame) -> DataFrame:
        """triples with frag_id: three lookups make the cell, one broadcast of the cell table (a row for each cell
        that occurs) the fragment. Cells not seen before belong to the remainder, fragment 0 if there is none."""
        spark = triples.sparkSession
        rows = [(*c, n) for c, n in self.of_cell.items()] or [("", "", "", 0)]
        known = spark.createDataFrame(rows, "s_cell string, p_cell string, o_cell string, frag_id int")
        late = self.remainder.number if self.remainder else 0
        coded = triples.withColumns(self.cells.columns())
        return coded.join(F.broadcast(known), ["s_cell", "p_cell", "o_cell"], "left").withColumn("frag_id", F.coalesce("frag_id", F.lit(late))).select(*triples.columns, "frag_id")


def frequencies(fragments: list[Fragment], a: Analysis, predicates: list[Predicate], mode: str = "pattern_sum", filter_aware: bool = False) -> None:
    """Sets each fragment's access frequency: the sum over patterns that overlap it, the weight of the queries that
    have one, or (closest) the sum over patterns whose constants are exactly its positive predicates."""
    masks = pattern_masks(a, predicates, filter_aware)
    for f in fragments:
        hit = [(k, need, w) for k, need, w in masks if f.bits & need == need]
        if mode == "closest":
            f.freq = sum(w for _, need, w in hit if need == f.bits)
        elif mode == "query_count":
            f.freq = sum(a.weights[q] for q in {q for k, _, _ in hit for q in a.occurrences.get(k, ())})
        else:
            f.freq = sum(w for _, _, w in hit)


def fragment(a: Analysis, triples: DataFrame, predicates: list[Predicate] | None = None, signature: str = "pattern_set", mode: str = "pattern_sum", filter_aware: bool = True, fraction: float | None = None, remainder_scope: str = "all_negated") -> Fragmentation:
    """Predicates, one counting scan (of all triples or of a sample), reduction, fragments numbered by their cells."""
    s = extract(a) if predicates is None else list(predicates)
    base = Cells(s)
    counted = histogram(triples, base, fraction)
    return assemble(a, s, base, counted, signature, mode, filter_aware, remainder_scope)


def assemble(a: Analysis, s: list[Predicate], base: Cells, counted: list, signature: str = "pattern_set", mode: str = "pattern_sum", filter_aware: bool = True, remainder_scope: str = "all_negated") -> Fragmentation:
    truths = {c: base.truths(c) for c, _ in counted}
    kept = reduce_predicates(s, [(truths[c], n) for c, n in counted], a, signature, filter_aware)
    at = [s.index(p) for p in kept]
    groups: dict[int, Fragment] = {}
    for cell, n in counted:
        bits = sum((truths[cell] >> i & 1) << k for k, i in enumerate(at))
        f = groups.setdefault(bits, Fragment(0, bits, tuple(p for k, p in enumerate(kept) if bits >> k & 1), tuple(p for k, p in enumerate(kept) if not bits >> k & 1), 0))
        f.size += n
        f.cells.append(cell)
    # a fixed numbering: by the constants, not by the order in which counts arrive
    fragments = sorted(groups.values(), key=lambda f: (not f.bits, [str(p) for p in sorted(f.pos)]))
    for i, f in enumerate(fragments):
        f.number = i + 1
    frequencies(fragments, a, kept, mode)
    for f in fragments:
        f.remainder = f.bits == 0 if remainder_scope == "all_negated" else f.freq == 0
    return Fragmentation(kept, base, fragments, a, {c: f.number for f in fragments for c in f.cells}, len(s), dict(counted))


def uniform_load(fragments: list[Fragment], n: int) -> float:
    return sum(f.load for f in fragments) / n


def fragment_table(spark: SparkSession, fr: Fragmentation) -> DataFrame:
    """number, definition, frequency, size and load of the fragments, heaviest first."""
    rows = [(f.number, f.label(), f.freq, f.size, f.load, f.remainder) for f in sorted(fr.fragments, key=lambda f: (-f.load, f.number))]
    return spark.createDataFrame(rows, "frag_id int, definition string, freq long, size long, load long, is_remainder boolean")


def fragment_edges(fr: Fragmentation, mode: str = "edge_sum") -> dict[tuple[int, int], int]:
    """w(a, b), a < b: weights of pattern edges whose ends overlap the two fragments; or of their distinct queries."""
    need = {k: m for k, m, _ in pattern_masks(fr.analysis, fr.predicates)}
    over = {k: [f.number for f in fr.fragments if f.bits & m == m] for k, m in need.items()}
    edges: dict[tuple[int, int], int] = {}
    seen: dict[tuple[int, int], set[str]] = {}
    for a, b, w in fr.analysis.edges:
        pairs = {(min(x, y), max(x, y)) for x in over[a] for y in over[b] if x != y}
        for pair in pairs:
            edges[pair] = edges.get(pair, 0) + w
            seen.setdefault(pair, set()).update(fr.analysis.witnesses[a, b])
    if mode == "query_count":
        return {k: sum(fr.analysis.weights[q] for q in qs) for k, qs in seen.items()}
    return edges


def symbolic_relevant(fr: Fragmentation, t: TriplePattern, q: Query | None = None) -> list[Fragment]:
    """Fragments that may hold triples of a pattern with its raw constants and the query's filters: each fragment's
    predicates must agree with what is required of a component."""
    asked: dict[str, list[tuple[Predicate, bool]]] = {"s": [], "p": [], "o": []}
    constants = {c: x for c, x in t.parts() if isinstance(x, Term)}
    for c, op, v in filters_of(q, t) if q else ():
        asked[c].append((Predicate(c, op, v.text, v.kind), True))
    from loadshard.operators.predicates import component_satisfiable

    out = []
    for f in fr.fragments:
        fits = True
        for c in "spo":
            signs = [(p, p in f.pos) for p in fr.predicates if p.component == c] + asked[c]
            if c in constants:
                x = constants[c]
                fits = all(p.holds(x.text, x.kind, x.number) == yes for p, yes in signs)
            elif signs:
                fits = component_satisfiable(signs)
            if not fits:
                break
        if fits:
            out.append(f)
    return out
