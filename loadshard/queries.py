"""Registered queries of the library's methods, with SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard import oracles as O
from loadshard.baselines import by_property, central, khop, khop_view
from loadshard.functions.shared import fresh_path, materialize
from loadshard.operators import dictionary, sizing
from loadshard.operators.allocation import hash_site, place, second_round
from loadshard.operators.fragments import Fragmentation, fragment, fragment_edges, fragment_table
from loadshard.operators.predicates import extract, satisfiable_minterms
from loadshard.operators.store import Store, bootstrap, fragment_by_statistics, from_sites, pair_counts, site_summaries, virtual_store
from loadshard.plans.cost import moved_pages
from loadshard.plans.initial import access_path
from loadshard.plans.physical import Meter, execute, plan
from loadshard.query.ast import Query, Term, TriplePattern
from loadshard.query.compile import to_dataframe
from loadshard.sources.mapping import BY_NAME, MAPS, TYPE, branches, subjects_repeat, triple_view, triples
from loadshard.sources.placed import parts, sampled_fragments, table_counts, view_store
from loadshard.streaming import updates
from loadshard.workload.catalogue import CRAWL, HEAVY, SAMPLE, SAMPLE_TABLES, SAMPLE_THETA, crawl_load, query, text_of
from loadshard.workload.load import analyse, load_queries, pattern_edges, pattern_frequency, phi, term_frequency

Run = Callable[[SparkSession, str], DataFrame]
THETA, SITES = 2, 3
MINI = ("b05", "b08", "b16")
MINI_TABLES = ("orders", "customer", "nation")
_held: dict[tuple, object] = {}


def held(spark: SparkSession, key: tuple, make: Callable[[], object]) -> object:
    """Stores are built once for an application and input."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _held:
        _held[key] = make()
    return _held[key]


def written(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The triples of all tables, written once for all stores."""
    return held(spark, ("triples", sf_dir), lambda: materialize(triples(spark, sf_dir).sortWithinPartitions("p", "o", "s")))


def unrepeated(spark: SparkSession, sf_dir: str) -> tuple[str, ...]:
    """The tables that need no search for repeats, as their subjects were seen not to repeat."""
    return () if held(spark, ("repeats", sf_dir), lambda: subjects_repeat(spark, sf_dir, "lineitem")) else ("lineitem",)


def known(spark: SparkSession, sf_dir: str) -> dict:
    """Counts of all tables and whether a table's subjects repeat, for stores that are views."""
    return {"known": held(spark, ("counts", sf_dir), lambda: table_counts(spark, sf_dir)), "single": partial(single, spark, sf_dir)}


def built(spark: SparkSession, sf_dir: str, n: int = SITES, form: str = "smoothed") -> Store:
    """The fragmented store as a view of the given tables; nothing is written."""
    make = lambda: view_store(spark, sf_dir, analyse(load_queries(spark, crawl_load()), THETA), lambda fr: place(fr, n, form), unrepeated(spark, sf_dir), **known(spark, sf_dir))
    return held(spark, ("store", sf_dir, n, form), make)


def built_by_property(spark: SparkSession, sf_dir: str) -> Store:
    def make() -> Store:
        a = analyse(load_queries(spark, crawl_load()), THETA)
        return view_store(spark, sf_dir, a, lambda fr: place(fr, SITES, "balance"), unrepeated(spark, sf_dir), by_property.cuts_of(a), **known(spark, sf_dir), signature="none")

    return held(spark, ("byprop", sf_dir), make)


def single(spark: SparkSession, sf_dir: str, name: str) -> bool:
    """Whether each subject of a table was seen to have one row."""
    return held(spark, ("repeats" if name == "lineitem" else f"repeats {name}", sf_dir), lambda: subjects_repeat(spark, sf_dir, name)) is False


def built_khop(spark: SparkSession, sf_dir: str) -> khop_view.KHopView:
    """The parts as a view of the given tables; only what is told of hubs is written."""
    return held(spark, ("khop", sf_dir), lambda: khop_view.build(spark, sf_dir, SITES, single=partial(single, spark, sf_dir)))


def mini(spark: SparkSession, sf_dir: str, n: int = 2, signature: str = "none") -> Store:
    def make() -> Store:
        t = triples(spark, sf_dir, MINI_TABLES)
        fr = fragment(analyse(load_queries(spark, [(q, text_of(q), 1) for q in MINI]), 1), t, signature=signature)
        return virtual_store(t, fr, place(fr, n))

    return held(spark, ("mini", sf_dir, n, signature), make)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """B05 over the fragmented store of three tables on two sites."""
    return execute(query("b05"), mini(spark, sf_dir))


def on_store(qid: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return execute(query(qid), built(spark, sf_dir))


def viewed(spark: SparkSession, sf_dir: str, q: Query) -> DataFrame:
    """The triples as a view of the given tables, nothing written. Repeats are looked for where a query may meet lines."""
    names = [t.p.text if isinstance(t.p, Term) else None for g in q.branches for t in [*g.required, *(t for part in g.optional for t in part)]]
    lines = None in names or TYPE in names or any(p in names for p, *_ in branches(BY_NAME["lineitem"]))
    return triple_view(spark, sf_dir, unique=unrepeated(spark, sf_dir) if lines else ("lineitem",))


def on_central(qid: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return central.run(query(qid), viewed(spark, sf_dir, query(qid)))


def on_by_property(qid: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return execute(query(qid), built_by_property(spark, sf_dir))


def on_khop(qid: str, dedup: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return khop.run(query(qid), built_khop(spark, sf_dir), dedup)


def unpruned(qid: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return execute(query(qid), built(spark, sf_dir), prune=False)


def sample_fragmentation(spark: SparkSession, sf_dir: str, mode: str = "pattern_sum") -> Fragmentation:
    return fragment(analyse(load_queries(spark, SAMPLE), SAMPLE_THETA), triples(spark, sf_dir, SAMPLE_TABLES), signature="none", mode=mode)


def sample_frequency(mode: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return fragment_table(spark, sample_fragmentation(spark, sf_dir, mode)).select("definition", "freq", "size", "load")


def sample_edges(mode: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    fr = sample_fragmentation(spark, sf_dir)
    name = {f.number: f.label() for f in fr.fragments}
    rows = [(*sorted((name[a], name[b])), w) for (a, b), w in fragment_edges(fr, mode).items()]
    return spark.createDataFrame(rows, "a string, b string, w long")


def sample_trace(form: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each site would gain from each fragment, in the order in which they are placed."""
    fr = sample_fragmentation(spark, sf_dir)
    name = {f.number: f.label() for f in fr.fragments}
    p = place(fr, SITES, form, remainder_ratio=0)
    return spark.createDataFrame([(i + 1, name[f], *(round(x, 3) for x in scores), site) for i, (f, scores, site) in enumerate(p.trace)], "turn int, definition string, site1 double, site2 double, site3 double, chosen int")


def sample_allocation(form: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    fr = sample_fragmentation(spark, sf_dir)
    name = {f.number: f.label() for f in fr.fragments}
    p = place(fr, SITES, form, remainder_ratio=0)
    return spark.createDataFrame([(s.number, "; ".join(sorted(name[f] for f in s.fragments)), s.load) for s in p.sites], "site_id int, fragments string, load long")


def mini_fragments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fragment_table(spark, mini(spark, sf_dir).fragmentation).select("definition", "size", "freq", "load")


def mini_by_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fragment sizes from counts by property and by constant, without a count of cells."""
    a = analyse(load_queries(spark, [(q, text_of(q), 1) for q in MINI]), 1)
    t = mini(spark, sf_dir).triples
    stats = from_sites(site_summaries(t), pair_counts(t, extract(a)))
    return fragment_table(spark, fragment_by_statistics(a, stats, signature="none")).where("size > 0").select("definition", "size", "freq", "load")


def site_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics by property, merged from what each site tells of its triples."""
    stats = from_sites(site_summaries(built(spark, sf_dir).triples))
    return spark.createDataFrame([(p, s.rows, s.low, s.high) for p, s in stats.properties.items()], "p string, n long, low double, high double")


def mini_assignment(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = mini(spark, sf_dir)
    name = spark.createDataFrame([(f.number, f.label()) for f in st.fragmentation.fragments], "frag_id int, definition string")
    return st.triples.groupBy("frag_id").agg(F.count(F.lit(1)).alias("n"), F.min("s").alias("first"), F.max("s").alias("last")).join(F.broadcast(name), "frag_id").select("definition", "n", "first", "last")


def update_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A store of all tables but the events, after a batch of all events."""

    def make() -> Store:
        t = written(spark, sf_dir).where("s not like 'event:%'")
        fr = fragment(analyse(load_queries(spark, crawl_load()), THETA), t)
        store = bootstrap(spark, t, fr, place(fr, SITES), fresh_path(spark, "updated"))
        return updates.apply_batch(store, updates.from_events(spark.read.parquet(f"{sf_dir}/events.parquet")), 0)

    after = held(spark, ("updated", sf_dir), make).triples
    return after.groupBy("p").agg(F.count(F.lit(1)).alias("n"), F.min("o").alias("first"), F.max("o").alias("last"))


def routed(spark: SparkSession, sf_dir: str) -> DataFrame:
    ops = updates.from_events(spark.read.parquet(f"{sf_dir}/events.parquet"))
    return updates.route(ops, built(spark, sf_dir)).groupBy("op", "site_id", "frag_id").agg(F.count(F.lit(1)).alias("n"))


def site_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = built(spark, sf_dir)
    load = spark.createDataFrame([(s.number, s.load, s.load / st.placement.uniform) for s in st.placement.sites], "site_id int, load long, over_uniform double")
    return st.triples.groupBy("site_id").agg(F.count(F.lit(1)).alias("triples")).join(load, "site_id")


def planned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimated cost, pages moved, sites and fragments of every workload query, by store."""
    rows = []
    for name, st in (("workload", built(spark, sf_dir)), ("by_property", built_by_property(spark, sf_dir))):
        for q in [*CRAWL, *HEAVY]:
            ps = plan(query(q), st)
            rows.append((name, q, float(sum(p.cost for p in ps)), sum(moved_pages(p.root) for p in ps), len(set().union(*(p.sites for p in ps))), len(set().union(*(p.fragments for p in ps)))))
    return spark.createDataFrame(rows, "system string, query string, cost double, pages int, sites int, fragments int")


def sizing_curve(load: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    st = built(spark, sf_dir)
    items = CRAWL if load == "crawl" else HEAVY
    qs = [query(q) for q in items]
    return sizing.best_site_count(spark, st.fragmentation, st.stats, qs, dict.fromkeys(items, 1), list(range(1, 7)))


def transfer_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that really cross sites for one query of each class."""
    rows = []
    for name, st in (("workload", built(spark, sf_dir)), ("by_property", built_by_property(spark, sf_dir))):
        for q in ("b05", "b08", "b09", "b16"):
            m = Meter()
            execute(query(q), st, meter=m).write.format("noop").mode("overwrite").save()
            rows.append((name, q, sum(n for _, n in m.rows()), m.pages()))
    return spark.createDataFrame(rows, "system string, query string, rows long, pages long")


def ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Single-site queries and imbalance by allocation form, reduction signature and number of sites."""
    a = analyse(load_queries(spark, crawl_load()), THETA)
    t = built(spark, sf_dir)
    rows = []
    for signature in ("pattern_set", "access", "load", "none"):
        fr = fragment(a, t.triples, signature=signature)
        for form in ("smoothed", "damped", "balance", "affinity", "round_robin", "literal") if signature == "pattern_set" else ("smoothed",):
            for n in (2, 3, 5):
                p = place(fr, n, form)
                st = Store(None, fr, p, t.stats)
                single = sum(len(set().union(*(x.sites for x in plan(query(q), st)))) == 1 for q in CRAWL)
                rows.append((signature, form, n, len(fr.fragments), single, float(p.imbalance)))
    return spark.createDataFrame(rows, "signature string, form string, n int, fragments int, single_site int, imbalance double")


def sampled_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of fragment sizes from samples of subjects."""
    st = built(spark, sf_dir)
    exact = {f.label(): f.size for f in st.fragmentation.fragments}
    rows = []
    fr = st.fragmentation
    for share, got in sampled_fragments(fr.analysis, parts(spark, sf_dir, unrepeated(spark, sf_dir)), fr.predicates, (0.01, 0.05, 0.1), signature="none").items():
        found = {f.label(): f.size for f in got.fragments}
        rows += [(share, k, n, found.get(k, 0), abs(found.get(k, 0) - n) / n) for k, n in exact.items() if n]
    return spark.createDataFrame(rows, "fraction double, definition string, size long, estimate long, error double")


def replicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = built(spark, sf_dir)
    rows = []
    for share in (0.0, 0.05, 0.2):
        p = second_round(st.placement, st.fragmentation, share * st.stats.total)
        s2 = Store(None, st.fragmentation, p, st.stats)
        single = sum(len(set().union(*(x.sites for x in plan(query(q), s2)))) == 1 for q in CRAWL)
        extra = sum(next(f.size for f in st.fragmentation.fragments if f.number == k) * len(v) for k, v in p.copies.items())
        rows.append((share, single, 1 + extra / st.stats.total, float(sum(sum(x.cost for x in plan(query(q), s2)) for q in CRAWL))))
    return spark.createDataFrame(rows, "budget double, single_site int, storage_factor double, cost double")


def khop_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return built_khop(spark, sf_dir).measures()


def khop_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers that replication repeats in each sub-pattern, and that ownership removes."""
    one = lambda q: khop.duplicates(query(q), built_khop(spark, sf_dir)).select(F.lit(q).alias("query"), "branch", "part", "found", "kept", "removed")
    return reduce(DataFrame.union, [one(q) for q in ("b01", "b05", "b08", "b10", "b12", "b16", "s6")])


def rows_of_patterns(spark: SparkSession, sf_dir: str, patterns: list[TriplePattern]) -> dict[tuple[str, str | None, str | None], int]:
    """(property, constant, kind) -> rows of the given tables that a pattern of constant property stands for: one scan of each
    table that has one of the properties, without a shuffle of rows."""
    asked = {constants_of(t): 0 for t in patterns}
    for m in MAPS:
        found = [(key, F.count(F.when(o.isNotNull() if key[1] is None else (o == key[1]), 1))) for p, o, kind, _ in branches(m) for key in asked if key[0] == p and key[2] in (None, kind)]
        if found:
            got = spark.read.parquet(f"{sf_dir}/{m.name}.parquet").agg(*(n.alias(f"n{i}") for i, (_, n) in enumerate(found))).first()
            for (key, _), n in zip(found, got, strict=True):
                asked[key] += n
    return asked


def constants_of(t: TriplePattern) -> tuple[str, str | None, str | None]:
    return (t.p.text, t.o.text, t.o.kind) if isinstance(t.o, Term) else (t.p.text, None, None)


def crawl_patterns() -> dict[str, tuple[TriplePattern, ...]]:
    return {q: query(q).branches[0].required for q in CRAWL}


def khop_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each query stays inside the parts, with the rows that its patterns stand for."""
    of = crawl_patterns()
    n = rows_of_patterns(spark, sf_dir, [t for ts in of.values() for t in ts])
    return spark.createDataFrame([(q, khop.is_pwoc(list(ts), 2), sum(n[constants_of(t)] for t in ts)) for q, ts in of.items()], "query string, local boolean, n long")


def access_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The access paths of each pattern, with the rows that it stands for."""
    of = crawl_patterns()
    n = rows_of_patterns(spark, sf_dir, [t for ts in of.values() for t in ts])
    return spark.createDataFrame([(q, i, name, v, n[constants_of(t)]) for q, ts in of.items() for i, t in enumerate(ts) for name, v in access_path(t)], "query string, pattern int, path string, sorted_by string, n long")


def predicate_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The simple predicates of the sample load, with the triples of its tables for which each holds."""
    ps = extract(analyse(load_queries(spark, SAMPLE), SAMPLE_THETA))
    got = triples(spark, sf_dir, SAMPLE_TABLES).agg(*(F.count(F.when(p.column(), 1)).alias(f"n{i}") for i, p in enumerate(ps))).first()
    return spark.createDataFrame([(p.component, p.op, p.value, n) for p, n in zip(ps, got, strict=True)], "component string, op string, value string, n long")


def minterm_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = extract(analyse(load_queries(spark, SAMPLE), SAMPLE_THETA))
    kept = [p for p in s if p.op == "="]
    fr = sample_fragmentation(spark, sf_dir)
    return spark.createDataFrame([("sign vectors", 2 ** len(s)), ("satisfiable", len(satisfiable_minterms(s))), ("satisfiable without ranges", len(satisfiable_minterms(kept))), ("observed", len(fr.fragments))], "what string, n long")


def remainder_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return triple_view(spark, sf_dir, ("pages", "benchmark", "part")).select(hash_site(3).alias("site_id")).groupBy("site_id").agg(F.count(F.lit(1)).alias("n"))


def crawl_rows(fn: Callable[..., DataFrame], *columns: str) -> Run:
    return lambda spark, _: fn(load_queries(spark, crawl_load()).rows).select(*columns)


QUERIES: dict[str, Run] = {
    "triples_by_property": lambda s, d: triples(s, d).groupBy("p").agg(F.count(F.lit(1)).alias("n")),
    "triples_distinct_count": lambda s, d: triples(s, d).agg(F.count(F.lit(1)).alias("n")),
    "dictionary_ids": lambda s, d: dictionary.build(triples(s, d, MINI_TABLES)),
    "load_term_frequency": crawl_rows(term_frequency, "term", "kind", "freq"),
    "phi_patterns": crawl_rows(partial(phi, theta=THETA), "pattern"),
    "pattern_frequency": crawl_rows(partial(pattern_frequency, theta=THETA), "pattern", "freq"),
    "query_graph_edges": crawl_rows(partial(pattern_edges, theta=THETA), "a", "b", "w"),
    "simple_predicates": predicate_rows,
    "minterm_counts": minterm_counts,
    "fragment_sizes_exact": mini_fragments,
    "fragment_sizes_statistics": mini_by_statistics,
    "fragment_assignment_hash": mini_assignment,
    **{f"fragment_frequency_{m}": partial(sample_frequency, m) for m in ("pattern_sum", "query_count", "closest")},
    **{f"fragment_edges_{m}": partial(sample_edges, m) for m in ("edge_sum", "query_count")},
    **{f"benefit_trace_{f}": partial(sample_trace, f) for f in O.SCORES},
    **{f"allocation_{f}": partial(sample_allocation, f) for f in O.SCORES},
    "remainder_split": remainder_split,
    "flagship": flagship,
    **{q: partial(on_store, q) for q in [*CRAWL, *HEAVY]},
    **{f"central_{q}": partial(on_central, q) for q in ("b01", "b05", "b07", "b10", "b12", "b16", "b18", "s4", "s6", "s11")},
    **{f"byprop_{q}": partial(on_by_property, q) for q in ("b01", "b05", "b07", "b10", "b16", "s7")},
    **{f"khop_owned_{q}": partial(on_khop, q, "owned") for q in ("b01", "b05", "b08", "b10", "b12", "b16", "s6")},
    **{f"khop_distinct_{q}": partial(on_khop, q, "distinct") for q in ("b05", "b08", "b16")},
    **{f"unpruned_{q}": partial(unpruned, q) for q in ("b05", "b16")},
    "update_after_batch": update_counts,
    "route_ops": routed,
    "site_balance": site_balance,
    "plan_costs": planned,
    "sizing_curve_crawl": partial(sizing_curve, "crawl"),
    "sizing_curve_heavy": partial(sizing_curve, "heavy"),
    "transfer_pages": transfer_pages,
    "ablations": ablations,
    "sampled_sizes": sampled_sizes,
    "replication_round": replicated,
    "khop_parts": khop_measures,
    "khop_duplicates": khop_duplicates,
    "site_statistics": site_statistics,
    "khop_local_queries": khop_local,
    "access_paths": access_paths,
}

_MINI = ("CASE WHEN p = 'p:o_custkey' THEN 'p = p:o_custkey' WHEN p = 'p:c_nationkey' THEN 'p = p:c_nationkey' WHEN p = 'p:n_regionkey' AND o = 'region:2' THEN 'o = region:2 & p = p:n_regionkey' WHEN p = 'p:n_regionkey' THEN 'p = p:n_regionkey' "
         "WHEN p = 'p:o_orderstatus' AND o = 'F' THEN 'o = F & p = p:o_orderstatus' WHEN p = 'p:o_orderstatus' THEN 'p = p:o_orderstatus' WHEN p = 'p:o_orderpriority' AND o = '1-URGENT' THEN 'o = 1-URGENT & p = p:o_orderpriority' "
         "WHEN p = 'p:o_orderpriority' THEN 'p = p:o_orderpriority' WHEN p = 'p:c_mktsegment' THEN 'p = p:c_mktsegment' ELSE 'all negated' END")  # fmt: skip
_FREQ = "('p = p:o_custkey', 3), ('p = p:c_nationkey', 2), ('o = region:2 & p = p:n_regionkey', 1), ('p = p:n_regionkey', 0), ('o = F & p = p:o_orderstatus', 2), ('p = p:o_orderstatus', 0), ('o = 1-URGENT & p = p:o_orderpriority', 2), ('p = p:o_orderpriority', 1), ('p = p:c_mktsegment', 1), ('all negated', 0)"
def _load(body: str, items=O.CRAWL) -> str:
    return f"WITH {O.load_cte(items)}, {O.TERMS}, {O.normalized(THETA)}, {O.SEATS} {body}"


_MINI_SIZES = f"WITH {O.tri(MINI_TABLES)}, f AS (SELECT {_MINI} AS definition, count(*) AS size FROM tri GROUP BY 1), q AS (SELECT * FROM (VALUES {_FREQ}) v(definition, freq)) SELECT f.definition, f.size, q.freq, q.freq * f.size AS load FROM f JOIN q USING (definition)"
_UPDATE = """, ev AS (SELECT * FROM events), live AS (SELECT e.* FROM ev e WHERE e.event_type <> 'error' AND NOT EXISTS (SELECT 1 FROM ev x WHERE x.event_id = e.event_id + 1 AND x.event_type = 'error')),
buy AS (SELECT 'customer:' || user_id AS s, arg_max(CAST(CAST(value AS DECIMAL(18,2)) AS VARCHAR), event_id) AS o FROM ev WHERE event_type = 'purchase' GROUP BY user_id),
sign AS (SELECT DISTINCT 'customer:' || user_id AS s FROM ev WHERE event_type = 'signup'),
alln AS (SELECT s, p, CASE WHEN p = 'p:c_mktsegment' AND s IN (SELECT s FROM sign) THEN 'BUILDING' ELSE o END AS o FROM tri
 UNION ALL SELECT s, 'p:last_purchase', o FROM buy UNION ALL SELECT s, 'p:c_mktsegment', 'BUILDING' FROM sign WHERE s NOT IN (SELECT s FROM tri WHERE p = 'p:c_mktsegment')
 UNION ALL SELECT 'event:' || event_id, 'rdf:type', 'class:event' FROM live UNION ALL SELECT 'event:' || event_id, 'p:user_id', 'customer:' || user_id FROM live
 UNION ALL SELECT 'event:' || event_id, 'p:ts', CAST(epoch_us(ts) AS VARCHAR) FROM live UNION ALL SELECT 'event:' || event_id, 'p:event_type', event_type FROM live
 UNION ALL SELECT 'event:' || event_id, 'p:value', CAST(CAST(value AS DECIMAL(18,2)) AS VARCHAR) FROM live UNION ALL SELECT 'event:' || event_id, 'p:k', json_extract_string(props, '$.k') FROM live)
SELECT p, count(*) AS n, min(o) AS first, max(o) AS last FROM alln GROUP BY p"""

ORACLES: dict[str, str] = {
    "triples_by_property": f"WITH {O.tri()} SELECT p, count(*) AS n FROM tri GROUP BY p",
    "triples_distinct_count": f"WITH {O.tri()} SELECT count(*) AS n FROM tri",
    "dictionary_ids": f"WITH {O.tri(MINI_TABLES)}, t AS (SELECT s AS term, 'iri' AS kind FROM tri UNION SELECT p, 'iri' FROM tri UNION SELECT o, o_kind FROM tri) SELECT term, kind, row_number() OVER (ORDER BY term, kind) AS id FROM t",
    "load_term_frequency": f"WITH {O.load_cte(O.CRAWL)}, {O.TERMS} SELECT term, kind, freq FROM freq",
    "phi_patterns": _load("SELECT DISTINCT pattern FROM occ"),
    "pattern_frequency": _load("SELECT pattern, CAST(sum(weight) AS BIGINT) AS freq FROM (SELECT DISTINCT query_id, weight, pattern FROM occ) GROUP BY pattern"),
    "query_graph_edges": _load(O.EDGE_SQL),
    "simple_predicates": O.SAMPLE_PREDICATES,
    "minterm_counts": O.SAMPLE_MINTERMS,
    "fragment_sizes_exact": _MINI_SIZES,
    "fragment_sizes_statistics": _MINI_SIZES,
    "fragment_assignment_hash": f"WITH {O.tri(MINI_TABLES)} SELECT {_MINI} AS definition, count(*) AS n, min(s) AS first, max(s) AS last FROM tri GROUP BY 1",
    **{f"fragment_frequency_{m}": O.sample_frequency(m) for m in ("pattern_sum", "query_count", "closest")},
    **{f"fragment_edges_{m}": O.sample_edges(m) for m in ("edge_sum", "query_count")},
    **{f"benefit_trace_{f}": O.sample_trace(f) for f in O.SCORES},
    **{f"allocation_{f}": O.sample_allocation(f) for f in O.SCORES},
    "access_paths": _load(O.access_paths()),
    "site_statistics": f"WITH {O.tri()} SELECT p, count(*) AS n, min(o_num) AS low, max(o_num) AS high FROM tri GROUP BY p",
    "remainder_split": f"WITH {O.tri(('pages', 'benchmark', 'part'))} SELECT CAST(('0x' || substr(md5(s), 1, 8))::BIGINT % 3 + 1 AS INTEGER) AS site_id, count(*) AS n FROM tri GROUP BY 1",
    "flagship": O.of_query("b05"),
    "update_after_batch": f"WITH {O.tri(tuple(m.name for m in MAPS if m.name != 'events'))}{_UPDATE}",
    "khop_local_queries": O.khop_local([(q, q not in ("b03", "b04", "b05", "b07", "b10", "b11", "b12")) for q in CRAWL]),
    **{q: O.of_query(q.rsplit("_", 1)[-1]) for q in QUERIES if q.rsplit("_", 1)[-1] in {**CRAWL, **HEAVY}},
}
