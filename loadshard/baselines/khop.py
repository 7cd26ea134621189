"""k-hop baseline: the entity graph is partitioned, each part owns its subjects' triples and holds copies of all
triples within k directed hops. Queries that have a core vertex run inside the parts; others are decomposed."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from loadshard.baselines.khop_view import KHopView
from loadshard.functions.shared import materialize
from loadshard.query.ast import GraphPattern, Query, TriplePattern, Var
from loadshard.query.compile import Scope, finish_pattern, finish_query, join_order, natural, spread
from loadshard.sources.placed import narrowing


@dataclass
class KHop:
    triples: DataFrame  # s, p, o, o_kind, o_num, part_id, owned
    n: int
    k: int
    labels: DataFrame


def entity_edges(triples: DataFrame, with_types: bool = False) -> DataFrame:
    """(a, b): triples that join two subjects; type edges are left out unless asked for, as classes are hubs."""
    e = triples.where("o_kind = 'iri'" + ("" if with_types else " and p <> 'rdf:type'")).select(F.col("s").alias("a"), F.col("o").alias("b"))
    return e.join(triples.select(F.col("s").alias("b")).distinct(), "b", "left_semi").select("a", "b").distinct()


def partition(triples: DataFrame, n: int, method: str = "label_propagation", rounds: int = 3, slack: float = 1.15, with_types: bool = False) -> DataFrame:
    """(s, part_id) for every subject.

    Label propagation starts from a hash. In each round a vertex wishes for its neighbours' commonest part; wishes
    for a part beyond ``slack`` times the mean size are granted by a hash of the vertex in proportion to its room, so
    parts stay bounded without a global sort."""
    start = (F.conv(F.substring(F.md5("s"), 1, 8), 16, 10).cast("long") % n).cast("int")
    labels = materialize(triples.select("s").distinct().withColumn("part_id", start))
    if method == "hash":
        return labels
    edges = entity_edges(triples, with_types)
    both = materialize(edges.union(edges.select("b", "a")))
    cap = slack * labels.count() / n
    for turn in range(rounds):
        votes = both.join(labels.select(F.col("s").alias("b"), "part_id"), "b").groupBy("a", "part_id").agg(F.count(F.lit(1)).alias("w"))
        wish = votes.groupBy(F.col("a").alias("s")).agg(F.max(F.struct("w", (-F.col("part_id")).alias("less"))).alias("best")).select("s", (-F.col("best.less")).cast("int").alias("to"))
        asked = labels.join(wish, "s", "left").withColumn("to", F.coalesce("to", "part_id"))
        stay = asked.where("to = part_id").groupBy("to").agg(F.count(F.lit(1)).alias("stay"))
        want = asked.where("to <> part_id").groupBy("to").agg(F.count(F.lit(1)).alias("want"))
        share = want.join(stay, "to", "left").select("to", F.least(F.lit(1.0), F.greatest(F.lit(0.0), (F.lit(cap) - F.coalesce("stay", F.lit(0))) / F.col("want"))).alias("share"))
        lot = F.pmod(F.xxhash64("s", F.lit(turn)), F.lit(10_000)) / 10_000
        labels = materialize(asked.join(F.broadcast(share), "to", "left").select("s", F.when((F.col("to") != F.col("part_id")) & (lot < F.col("share")), F.col("to")).otherwise(F.col("part_id")).alias("part_id")))
    return labels


def replicate(triples: DataFrame, labels: DataFrame, n: int, k: int = 2) -> KHop:
    """Owned triples, then k - 1 rounds that fetch the triples of the objects at the frontier."""
    owned = materialize(triples.join(labels, "s").withColumn("owned", F.lit(True)))
    every = owned.select("s", "part_id").distinct()
    frontier, copies = owned, []
    plain = owned.drop("part_id", "owned")
    for _ in range(k - 1):
        reach = frontier.where("o_kind = 'iri'").select(F.col("o").alias("s"), "part_id").distinct().join(every, ["s", "part_id"], "left_anti")
        got = materialize(plain.join(reach, "s").withColumn("owned", F.lit(False)))
        copies.append(got)
        every = every.union(got.select("s", "part_id").distinct())
        frontier = got
    cols = ["s", "p", "o", "o_kind", "o_num", "part_id", "owned"]
    return KHop(reduce(DataFrame.union, [x.select(*cols) for x in (owned, *copies)]), n, k, labels)


def build(triples: DataFrame, n: int, k: int = 2, method: str = "label_propagation") -> KHop:
    return replicate(triples, partition(triples, n, method), n, k)


def _hops(patterns: list[TriplePattern], core: str) -> dict[str, int]:
    dist = {core: 0}
    changed = True
    while changed:
        changed = False
        for t in patterns:
            if isinstance(t.s, Var) and t.s.name in dist and isinstance(t.o, Var) and dist.get(t.o.name, 1 << 30) > dist[t.s.name] + 1:
                dist[t.o.name] = dist[t.s.name] + 1
                changed = True
    return dist


def core_vertex(patterns: list[TriplePattern], k: int) -> str | None:
    """A subject variable from which every pattern lies within k directed hops."""
    for v in dict.fromkeys(t.s.name for t in patterns if isinstance(t.s, Var)):
        dist = _hops(patterns, v)
        if all(isinstance(t.s, Var) and dist.get(t.s.name, k) + 1 <= k for t in patterns):
            return v
    return None


def is_pwoc(patterns: list[TriplePattern], k: int) -> bool:
    """Whether a graph pattern can be answered inside the parts, without communication."""
    if len(patterns) == 1:
        return True
    return core_vertex(list(patterns), k) is not None


def decompose(patterns: list[TriplePattern], k: int) -> list[list[TriplePattern]]:
    """Sub-patterns that each have a core: the vertex that covers most of what is left goes first."""
    left, out = list(patterns), []
    while left:
        best: list[TriplePattern] = [left[0]]
        for v in dict.fromkeys(t.s.name for t in left if isinstance(t.s, Var)):
            dist = _hops(left, v)
            got = [t for t in left if isinstance(t.s, Var) and dist.get(t.s.name, k) + 1 <= k]
            if len(got) > len(best):
                best = got
        out.append(best)
        left = [t for t in left if t not in best]
    return out


def core_rows(store: KHop | KHopView, scope: Scope, patterns: list[TriplePattern], owned: bool = False, home: bool = False) -> tuple[str | None, DataFrame]:
    """(core vertex, answers) of one sub-pattern in all parts at once, part_id being a join key; copies answer too. Over a
    view ``owned`` takes only answers whose core vertex is owned, and ``home`` adds home_, the core vertex's owner."""
    core = core_vertex(patterns, store.k)
    bound = []
    if isinstance(store, KHopView):
        groups: dict[object, list[TriplePattern]] = {}
        for t in join_order(tuple(patterns)):
            groups.setdefault(t.s, []).append(t)
        for s, g in groups.items():
            mine = isinstance(s, Var) and s.name == core
            bound += store.bind(g, scope, core is None or owned and mine, home and mine)
        rows = bound.pop(0)
        while bound:  # those that share more than the part first
            at = next((i for i, x in enumerate(bound) if set(x.columns) & set(rows.columns) - {"part_id"}), 0)
            rows = natural(rows, bound.pop(at))
        return core, rows
    for t in join_order(tuple(patterns)):
        rows = store.triples.where(F.col("owned")) if core is None else store.triples
        bound.append(scope.bind(rows, t, ("part_id",)))
    return core, reduce(natural, bound)


def run_core(store: KHop | KHopView, scope: Scope, patterns: list[TriplePattern], dedup: str) -> DataFrame:
    """One sub-pattern without repeats. owned: an answer counts where its core vertex is owned, which costs a join with the
    owners, or none where the view tells them with the rows; distinct: answers of all parts are made distinct."""
    view = isinstance(store, KHopView)
    core, rows = core_rows(store, scope, patterns, dedup == "owned")
    if core is None or view and dedup == "owned":
        return rows.drop("part_id")
    if dedup == "owned":
        return rows.join(store.labels.select(F.col("s").alias(core), F.col("part_id")), [core, "part_id"], "left_semi").drop("part_id")
    return rows.drop("part_id").dropDuplicates()


def scope_of(q: Query, g: GraphPattern, store: KHop | KHopView) -> Scope:
    scope = Scope(g, {k for k, _ in q.order})
    scope.narrow = narrowing(g) if isinstance(store, KHopView) else None
    return scope


def run(q: Query, store: KHop | KHopView, dedup: str = "owned") -> DataFrame:
    done = []
    for g in q.branches:
        scope = scope_of(q, g, store)
        groups = [list(g.required)] if is_pwoc(list(g.required), store.k) else decompose(list(g.required), store.k)
        parts = [run_core(store, scope, p, dedup) for p in groups]
        left = list(zip(parts, groups, strict=True))
        whole, of = left.pop(0)
        while left:
            at = next((i for i, (x, _) in enumerate(left) if set(x.columns) & set(whole.columns)), 0)
            near, patterns = left.pop(at)
            whole, of = spread(whole, near, of, patterns, hint="shuffle_hash"), [*of, *patterns]
        if isinstance(store, KHopView):
            done.append(finish_pattern(g, whole, scope, lambda t: store.scan(True, t)))
            continue
        owned = store.triples.where("owned").drop("part_id", "owned")
        done.append(finish_pattern(g, whole, scope, lambda t: owned))
    return finish_query(q, done)


def duplicates(q: Query, store: KHop | KHopView) -> DataFrame:
    """(branch, part, found, kept, removed): answers of each sub-pattern that has a core over all parts, those that
    ownership keeps, and those that it removes as repeats of replication."""
    out = []
    for i, g in enumerate(q.branches):
        scope = scope_of(q, g, store)
        groups = [list(g.required)] if is_pwoc(list(g.required), store.k) else decompose(list(g.required), store.k)
        for j, patterns in enumerate(groups):
            core, rows = core_rows(store, scope, patterns, home=True)
            if core is None:
                continue
            if not isinstance(store, KHopView):
                rows = rows.join(store.labels.select(F.col("s").alias(core), F.col("part_id").alias("home_")), core)
            kept = F.coalesce(F.sum((F.col("part_id") == F.col("home_")).cast("long")), F.lit(0))
            n = rows.agg(F.count(F.lit(1)).alias("found"), kept.alias("kept"))
            out.append(n.select(F.lit(i).alias("branch"), F.lit(j).alias("part"), "found", "kept", (F.col("found") - F.col("kept")).alias("removed")))
    spark = store.spark if isinstance(store, KHopView) else store.triples.sparkSession
    empty = spark.createDataFrame([], "branch int, part int, found long, kept long, removed long")
    return reduce(DataFrame.union, out, empty)


def replication_factor(store: KHop) -> float:
    r = store.triples.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("owned").cast("long")).alias("own")).first()
    return r["n"] / r["own"]


def update_fanout(store: KHop, subjects: DataFrame) -> DataFrame:
    """(s, parts): how many parts an update of each subject touches."""
    return subjects.select("s").distinct().join(store.triples.select("s", "part_id").distinct(), "s").groupBy("s").agg(F.count(F.lit(1)).alias("parts"))


def edge_cut(triples: DataFrame, labels: DataFrame) -> float:
    e = entity_edges(triples)
    x, y = labels.select(F.col("s").alias("a"), F.col("part_id").alias("pa")), labels.select(F.col("s").alias("b"), F.col("part_id").alias("pb"))
    return e.join(x, "a").join(y, "b").agg(F.avg((F.col("pa") != F.col("pb")).cast("double"))).first()[0] or 0.0

