from __future__ import annotations

import itertools

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from loadshard.operators.allocation import allocate, benefit, place, rebalance, second_round
from loadshard.operators.fragments import fragment, fragment_edges, symbolic_relevant
from loadshard.operators.predicates import Cells, Predicate, component_satisfiable, enumerate_all, extract, satisfiable, satisfiable_minterms
from loadshard.query.ast import Term
from loadshard.sources.mapping import triples
from loadshard.workload import worked
from loadshard.workload.catalogue import CRAWL, SAMPLE, SAMPLE_TABLES, SAMPLE_THETA, crawl_load, query, text_of
from loadshard.workload.load import analyse, collapse_duplicates, load_queries, parse_log, term_frequency


def P(op, value, kind="num", c="o"):
    return Predicate(c, op, str(value), kind)


@pytest.fixture(scope="module")
def sample_analysis(spark):
    return analyse(load_queries(spark, SAMPLE), SAMPLE_THETA)


@pytest.fixture(scope="module")
def sample(spark, sf, sample_analysis):
    return fragment(sample_analysis, triples(spark, sf, SAMPLE_TABLES))


def test_load_analysis_of_the_sample(spark, sample_analysis):
    freq = {(r["term"], r["kind"]): r["freq"] for r in term_frequency(load_queries(spark, SAMPLE).rows).collect()}
    assert freq == {("region:1", "iri"): 7, ("BUILDING", "str"): 9, ("nation:7", "iri"): 1}
    kept = {o for p in sample_analysis.patterns.values() if (o := p.o) is not None}
    assert kept == {"region:1", "BUILDING"}
    assert {(p.op, p.value) for p in extract(sample_analysis) if p.op != "="} == {("<", "0"), (">=", "9000")}


def test_range_that_splits_nothing_is_dropped(spark, sf):
    load = [("a", "SELECT * { ?s s_acctbal ?b . FILTER(?b >= -100000) }", 3), ("b", "SELECT * { ?s s_name ?n }", 2), ("c", "SELECT * { ?s s_acctbal ?b }", 5)]
    fr = fragment(analyse(load_queries(spark, load), 2), triples(spark, sf, ("supplier",)))
    assert len(fr.predicates) == 2 and all(p.op == "=" for p in fr.predicates)


@pytest.mark.parametrize("signature,kept", [("pattern_set", True), ("load", True), ("access", False)])
def test_range_that_splits_stays_unless_filters_are_ignored(spark, sf, signature, kept):
    a = analyse(load_queries(spark, [*crawl_load(), ("s7", text_of("s7"), 3)]), 2)
    fr = fragment(a, triples(spark, sf), signature=signature, filter_aware=signature != "access")
    assert any(p.op == ">=" for p in fr.predicates) == kept


def test_complete_and_disjoint(spark, sf):
    t = triples(spark, sf)
    fr = fragment(analyse(load_queries(spark, crawl_load()), 2), t)
    counts = {r[0]: r[1] for r in fr.assign(t).groupBy("frag_id").count().collect()}
    assert counts == {f.number: f.size for f in fr.fragments}
    assert sum(counts.values()) == t.count()


def test_dropping_any_kept_predicate_changes_the_fragmentation(sample, sample_analysis):
    from loadshard.operators.fragments import pattern_masks

    fr = sample
    masks = pattern_masks(sample_analysis, fr.predicates, True)
    met = lambda f: frozenset(k for k, need, _ in masks if f.bits & need == need)
    for i in range(len(fr.predicates)):
        groups: dict = {}
        for f in fr.fragments:
            groups.setdefault(f.bits & ~(1 << i), set()).add(met(f))
        assert any(len(g) > 1 for g in groups.values())


@pytest.mark.parametrize(
    "signs,ok",
    [
        ([(P("=", 7), True), (P(">=", 5), True)], True), ([(P("=", 3), True), (P(">=", 5), True)], False), ([(P("=", "x", "str"), True), (P(">=", 5), True)], False), ([(P("=", "x", "str"), True), (P(">=", 5), False)], True),
        ([(P("=", 1), True), (P("=", 2), True)], False), ([(P(">", 5), True), (P("<", 4), True)], False), ([(P(">", 5), True), (P("<=", 5), True)], False), ([(P(">=", 5), True), (P("<=", 5), True)], True),
        ([(P(">=", 5), True), (P("<=", 5), True), (P("=", 5), False)], False), ([(P("isIRI", ""), True), (P("isLiteral", ""), True)], False), ([(P("isIRI", ""), True), (P(">=", 5), True)], False), ([(P("isIRI", ""), False), (P("isNumeric", ""), False)], True),
    ],
)
def test_satisfiability(signs, ok):
    assert component_satisfiable(signs) == ok


preds = st.lists(st.sampled_from([P("=", 1), P("=", 4), P("=", "a", "str"), P(">=", 2), P("<", 4), P("isLiteral", ""), Predicate("p", "=", "x"), Predicate("p", "=", "y"), Predicate("s", "=", "z")]), min_size=1, max_size=7, unique=True)


@given(preds)
@settings(max_examples=60, deadline=None)
def test_cell_product_is_the_satisfiable_part_of_all_minterms(s):
    every = {v for v in enumerate_all(s) if satisfiable(list(zip(s, v, strict=True)))}
    assert set(satisfiable_minterms(s)) == every


@given(preds, st.lists(st.tuples(st.sampled_from(["z", "q"]), st.sampled_from(["x", "y", "w"]), st.sampled_from([("1", "num", 1.0), ("4", "num", 4.0), ("2", "num", 2.0), ("a", "str", None), ("i", "iri", None)])), min_size=1, max_size=5))
@settings(max_examples=60, deadline=None)
def test_cells_tell_every_truth(s, rows):
    cells = Cells(s)
    for subj, prop, (o, kind, n) in rows:
        code = tuple(".".join(map(str, cells.code(c, t, k, x))) for c, t, k, x in (("s", subj, "iri", None), ("p", prop, "iri", None), ("o", o, kind, n)))
        term = {"s": (subj, "iri", None), "p": (prop, "iri", None), "o": (o, kind, n)}
        assert cells.truths(code) == sum(p.holds(*term[p.component]) << i for i, p in enumerate(s))


def test_cell_columns_agree_with_the_driver(spark):
    s = [P(">=", 5), P("<", 9), P("=", 7), P("=", "7", "str"), P("isIRI", ""), Predicate("o", "contains", "b", "str")]
    rows = [("s", "p", o, k, n) for o, k, n in (("7", "num", 7.0), ("7", "str", None), ("5", "num", 5.0), ("9", "num", 9.0), ("4", "num", 4.0), ("abc", "str", None), ("n:b", "iri", None), ("6", "ts", 6.0))]
    cells = Cells(s)
    got = spark.createDataFrame(rows, "s string, p string, o string, o_kind string, o_num double").select("o", "o_kind", "o_num", *[v.alias(k) for k, v in cells.columns().items()]).collect()
    for r in got:
        assert cells.truths((r["s_cell"], r["p_cell"], r["o_cell"])) == sum(p.holds(r["o"], r["o_kind"], r["o_num"]) << i for i, p in enumerate(s))


def test_relevant_fragments_hold_all_matches(spark, sf):
    from loadshard.query.compile import matches
    t = triples(spark, sf)
    fr = fragment(analyse(load_queries(spark, crawl_load()), 5), t)
    placed = fr.assign(t).cache()
    for q in ("b05", "b07", "b12", "b15", "b29"):
        for p in query(q).branches[0].required:
            seen = {r[0] for r in placed.where(matches(p)).select("frag_id").distinct().collect()}
            assert seen <= {f.number for f in symbolic_relevant(fr, p, query(q))}
    placed.unpersist()


def test_benefit_values():
    u = sum(f.load for f in worked.table() if not f.remainder) / 3
    assert round(benefit([0], 22000, u), 2) == 0.85
    assert benefit([], 0, u) == 2
    assert benefit([], 0, u, "literal") == 0


def test_capacity(sample):
    edges, total = fragment_edges(sample), sum(f.size for f in sample.fragments)
    p = allocate(sample.fragments, edges, 3, capacity=0.5 * total, remainder_ratio=0)
    assert all(s.used <= 0.5 * total for s in p.sites) and sum(s.used for s in p.sites) == pytest.approx(total)
    with pytest.warns(UserWarning, match="no site has room"):
        allocate(sample.fragments, edges, 3, capacity=1, remainder_ratio=0)


def test_greedy_against_every_placement(sample):
    frags = [f for f in sample.fragments if not f.remainder and f.freq]
    edges = {k: w for k, w in fragment_edges(sample).items() if set(k) <= {f.number for f in frags}}
    p = allocate(frags, edges, 3)
    kept = lambda home: sum(w for (a, b), w in edges.items() if home[a] == home[b])
    best = max(kept(dict(zip([f.number for f in frags], h, strict=True))) for h in itertools.product((1, 2, 3), repeat=len(frags)))
    assert kept(p.site_of) >= 0.5 * best


def test_co_location_against_balance(spark, sf):
    """More queries stay on one site, at the price of balance."""
    from loadshard.operators.store import Store, statistics
    from loadshard.plans.physical import plan
    t = triples(spark, sf)
    fr = fragment(analyse(load_queries(spark, crawl_load()), 2), t)
    stats = statistics(t, fr)
    single, over = {}, {}
    for form in ("smoothed", "balance"):
        p = place(fr, 3, form)
        single[form] = sum(len(set().union(*(x.sites for x in plan(query(q), Store(None, fr, p, stats))))) == 1 for q in CRAWL)
        over[form] = p.imbalance
    assert single["smoothed"] > single["balance"] and over["smoothed"] > over["balance"]
    p = place(fr, 3)
    assert rebalance(p, fr, 1.2)
    more = second_round(p, fr, 0.2 * stats.total)
    assert more.copies and all(p.site_of[f] not in s for f, s in more.copies.items())


def test_log_forms(spark):
    log = spark.createDataFrame([("SELECT * { ?s q:label ?n }",), ("SELECT *  { ?s q:label ?n }",), ("broken {",)], "text string")
    got = collapse_duplicates(log)
    assert sorted(r["weight"] for r in got.collect()) == [1, 2]
    rows = parse_log(got).collect()
    assert len(rows) == 1 and rows[0]["p"] == "q:label" and rows[0]["weight"] == 2


def test_number_and_text_are_unlike():
    assert Term("1", "num") != Term("1", "str")
    assert not P("=", 1).holds("1", "str", None)
