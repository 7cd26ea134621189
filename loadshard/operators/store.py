"""The partitioned triple store: statistics, bootstrap in both modes, catalogue on disk."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import dataclass, field
from math import ceil

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.functions.shared import read_text, write_text
from loadshard.operators import layout
from loadshard.operators.allocation import Placement, Site, site_column
from loadshard.operators.fragments import Fragment, Fragmentation, assemble
from loadshard.operators.predicates import Cells, Predicate, extract
from loadshard.query.ast import GraphPattern, Term, TriplePattern, Var
from loadshard.workload.load import Analysis

PAGE = 1024
Star = Callable[[list, object], DataFrame | None]  # ((pattern, fragments, sites) each, scope) -> their join, if it is one scan
ROWS_PER_FILE = 4_000_000


@dataclass
class PropertyStats:
    rows: int
    subjects: int
    objects: int
    low: float | None = None
    high: float | None = None


@dataclass
class Statistics:
    """Counts for planning, of the size of the properties and of the load's constants."""

    total: int
    properties: dict[str, PropertyStats]
    pairs: dict[tuple[str, str, str], int] = field(default_factory=dict)  # (p, o, kind) of known constants
    subjects: int = 1
    objects: int = 1

    def rows(self, t: TriplePattern) -> float:
        """Expected triples of a pattern's constants."""
        p = t.p.text if isinstance(t.p, Term) else None
        if p is not None and p not in self.properties:
            return 0.0
        of = self.properties[p] if p else PropertyStats(self.total, self.subjects, self.objects)
        n = float(of.rows)
        if isinstance(t.o, Term):
            known = self.pairs.get((p, t.o.text, t.o.kind)) if p else None
            n = float(known) if known is not None else n / max(1, of.objects)
        if isinstance(t.s, Term):
            n /= max(1, of.subjects)
        return n

    def distinct(self, t: TriplePattern, name: str, rows: float) -> float:
        of = self.properties.get(t.p.text) if isinstance(t.p, Term) else None
        out = float("inf")
        for c, x in t.parts():
            if isinstance(x, Var) and x.name == name:
                n = {"s": of.subjects if of else self.subjects, "p": len(self.properties), "o": of.objects if of else self.objects}[c]
                out = min(out, n)
        return max(1.0, min(out, rows))


def statistics(triples: DataFrame, fr: Fragmentation | None = None, fraction: float | None = None) -> Statistics:
    """One aggregation by property (of all triples, or of a sample chosen by a hash of the subject); counts of constant
    pairs come from the cell counts that fragmentation has taken."""
    scale = 1
    if fraction is not None:
        scale = max(1, round(1 / fraction))
        triples = triples.where(F.pmod(F.xxhash64("s"), F.lit(scale)) == 0)
    aggs = [F.count(F.lit(1)).alias("n"), F.approx_count_distinct("s").alias("ds"), F.approx_count_distinct("o").alias("do"), F.min("o_num").alias("lo"), F.max("o_num").alias("hi")]
    got = triples.groupBy("p").agg(*aggs).collect()
    props = {r["p"]: PropertyStats(r["n"] * scale, r["ds"] * scale, min(r["do"] * scale, r["n"] * scale), r["lo"], r["hi"]) for r in got}
    total = sum(s.rows for s in props.values())
    return Statistics(total, props, counted_pairs(fr) if fr is not None else {}, max((s.subjects for s in props.values()), default=1), sum(s.objects for s in props.values()))


def counted_pairs(fr: Fragmentation) -> dict[tuple[str, str, str], int]:
    """(property, constant, kind) -> triples, from the cell counts."""
    ps, os_ = fr.cells.equal["p"], fr.cells.equal["o"]
    pairs = {(p.value, o.value, o.kind): 0 for p in ps for o in os_}
    sizes = {c: n for f in fr.fragments for c, n in zip(f.cells, _cell_sizes(fr, f), strict=True)}
    for (_, pc, oc), n in sizes.items():
        i, j = int(pc.split(".")[0]), int(oc.split(".")[0])
        if i and j:
            pairs[ps[i - 1].value, os_[j - 1].value, os_[j - 1].kind] += n
    return pairs


def site_summaries(triples: DataFrame, by: tuple[str, ...] = ("site_id",)) -> DataFrame:
    """(site_id, p, n, subjects, objects, low, high) of a store: what each site tells of its own triples, in one partially
    aggregated scan. Distinct subjects and objects are sketches, so that summaries can be merged. With frag_id in ``by``
    they are kept by partition, and an update replaces those of the partitions it rewrites."""
    objects = F.hll_sketch_agg(F.concat_ws("\x01", "o_kind", "o"))
    return triples.groupBy(*by, "p").agg(F.count(F.lit(1)).alias("n"), F.hll_sketch_agg("s").alias("subjects"), objects.alias("objects"), F.min("o_num").alias("low"), F.max("o_num").alias("high"))


def from_sites(summaries: DataFrame, pairs: dict[tuple[str, str, str], int] | None = None) -> Statistics:
    """Statistics of the whole from the sites' summaries, without the triples; ``pairs`` as in ``pair_counts``."""
    merged = lambda c: F.hll_sketch_estimate(F.hll_union_agg(c)).alias(c)
    got = summaries.groupBy("p").agg(F.sum("n").alias("n"), merged("subjects"), merged("objects"), F.min("low").alias("low"), F.max("high").alias("high")).collect()
    props = {r["p"]: PropertyStats(r["n"], min(r["subjects"], r["n"]), min(r["objects"], r["n"]), r["low"], r["high"]) for r in got}
    return Statistics(sum(s.rows for s in props.values()), props, dict(pairs or {}), max((s.subjects for s in props.values()), default=1), sum(s.objects for s in props.values()))


def pair_counts(triples: DataFrame, predicates: list[Predicate]) -> dict[tuple[str, str, str], int]:
    """(property, constant, kind) -> triples, for the constants that equality predicates ask of objects."""
    asked = sorted({(p.value, p.kind) for p in predicates if p.component == "o" and p.op == "="})
    if not asked:
        return {}
    wanted = triples.sparkSession.createDataFrame(asked, "o string, o_kind string")
    got = triples.join(F.broadcast(wanted), ["o", "o_kind"], "left_semi").groupBy("p", "o", "o_kind").count().collect()
    return {(r["p"], r["o"], r["o_kind"]): r["count"] for r in got}


def estimated_cells(stats: Statistics, cells: Cells) -> list[tuple[tuple[str, str, str], int]]:
    """(cell, expected triples) from statistics alone. A constant's share of a property is its pair count where pairs are
    known at all, else one of the property's distinct objects; subjects are taken as independent. Every cell that can
    occur is there, also at 0, so that a fragmentation made of it has a place for each triple. Statistics tell of equality only:
    other predicates raise ValueError (size them by a sample)."""
    if other := [p for p in cells.predicates if p.op != "="]:
        raise ValueError(f"statistics cannot size {other[0]}")
    code = lambda c, text, kind: ".".join(map(str, cells.code(c, text, kind, None)))
    none = "0.0.0"
    out: dict[tuple[str, str, str], float] = {}
    named = {p.value for p in cells.equal["p"]}
    for p in [*stats.properties, *sorted(named - set(stats.properties)), None]:
        of = stats.properties.get(p) or PropertyStats(0, 1, 1)
        pc = code("p", p, "iri") if p in named else none
        objects = {code("o", x.value, x.kind): stats.pairs.get((p, x.value, x.kind), 0) if stats.pairs else of.rows / max(1, of.objects) for x in cells.equal["o"]}
        if (told := sum(objects.values())) > of.rows:  # more constants than the property has objects
            objects = {k: n * of.rows / told for k, n in objects.items()}
        objects[none] = max(0, of.rows - told)
        subjects = {code("s", x.value, "iri"): 1 / max(1, of.subjects) for x in cells.equal["s"]}
        if (told := sum(subjects.values())) > 1:
            subjects = {k: x / told for k, x in subjects.items()}
        subjects[none] = max(0, 1 - told)
        for sc, share in subjects.items():
            for oc, n in objects.items():
                out[sc, pc, oc] = out.get((sc, pc, oc), 0) + share * n
    return sorted((c, round(n)) for c, n in out.items())


def fragment_by_statistics(a: Analysis, stats: Statistics, predicates: list[Predicate] | None = None, **options) -> Fragmentation:
    """Fragments whose sizes are estimated from statistics instead of counted; ``options`` are those of ``assemble``."""
    s = extract(a) if predicates is None else list(predicates)
    cells = Cells(s)
    return assemble(a, s, cells, estimated_cells(stats, cells), **options)


def _cell_sizes(fr: Fragmentation, f) -> list[int]:
    return [fr.cell_size.get(c, 0) for c in f.cells]


@dataclass
class Store:
    """Placed triples with what the planner knows of them."""

    triples: DataFrame  # s, p, o, o_kind, o_num, frag_id, site_id
    fragmentation: Fragmentation
    placement: Placement
    stats: Statistics
    path: str | None = None
    buckets: int = 0
    snapshot: layout.Snapshot | None = None
    narrow: Callable[[GraphPattern], Callable[[TriplePattern], Column]] | None = None  # conditions beside fragments and sites
    star: Star | None = None


def place_triples(triples: DataFrame, fr: Fragmentation, placement: Placement, key: str = "s") -> DataFrame:
    """Adds frag_id and site_id without a shuffle."""
    return fr.assign(triples).withColumn("site_id", site_column(placement, key))


def dealt(placed: DataFrame, fr: Fragmentation, placement: Placement, files_per_fragment: int = 1, rows_per_file: int = ROWS_PER_FILE, buckets: int = 0) -> DataFrame:
    """Placed triples shuffled by (site, fragment, salt) and sorted for writing. A fragment has as many salts as its counted
    size needs at ``rows_per_file``, at least ``files_per_fragment``, so that no task gets a large fragment whole. With
    buckets the salt is the subject's bucket, and the writer sorts."""
    if buckets:
        return placed.repartition("site_id", "frag_id", F.pmod(F.hash("s"), F.lit(buckets)))
    share = {f.number: ceil(f.size / (placement.n if f.number in placement.split else 1) / rows_per_file) for f in fr.fragments}
    rows = [(k, n) for k, n in share.items() if n > files_per_fragment]
    salts = F.lit(files_per_fragment)
    if rows:
        wanted = placed.sparkSession.createDataFrame(rows, "frag_id int, salts_ int")
        placed, salts = placed.join(F.broadcast(wanted), "frag_id", "left"), F.coalesce("salts_", salts)
    out = placed.repartition("site_id", "frag_id", F.pmod(F.xxhash64("s"), salts)).drop("salts_")
    return out.sortWithinPartitions("site_id", "frag_id", "p", "o", "s")


def distribute(triples: DataFrame, fr: Fragmentation, placement: Placement, path: str, mode: str = "route", files_per_fragment: int = 1, key: str = "s", rows_per_file: int = ROWS_PER_FILE, buckets: int = 0) -> None:
    """Writes the sites. route: one scan whose rows are shuffled by (site, fragment, salt), see ``dealt``; scan: every site filters all triples by its own fragments, without a shuffle.
    Files are sorted by (p, o, s), which gives narrow column statistics."""
    placed = place_triples(triples, fr, placement, key)
    if mode == "scan":
        for site in range(1, placement.n + 1):
            mine = placed.where(F.col("site_id") == site)
            layout.write(mine if buckets else mine.sortWithinPartitions("frag_id", "p", "o", "s"), path, 0, buckets, first=site == 1, more=site > 1)
        return
    layout.write(dealt(placed, fr, placement, files_per_fragment, rows_per_file, buckets), path, 0, buckets, first=True)


def bootstrap(spark: SparkSession, triples: DataFrame, fr: Fragmentation, placement: Placement, path: str, mode: str = "route", buckets: int | None = None) -> Store:
    """Writes the sites and opens them as a store. Triples are bucketed by subject within each fragment, so that joins on a
    subject need no exchange; None takes as many buckets as the largest fragment needs, or none at all where subjects are
    too uneven for that; 0 writes no buckets."""
    if buckets is None:
        buckets = layout.bucket_count(max((f.size for f in fr.fragments), default=0))
        buckets = buckets if layout.evenly_bucketed(triples, buckets) else 0
    distribute(triples, fr, placement, path, mode, buckets=buckets)
    everything = spark.read.schema(layout.SCHEMA).parquet(path)
    write_summaries(everything, path, 0)
    snapshot = layout.Snapshot(0, layout.parts_of_version(spark, path, 0))
    layout.commit(spark, path, snapshot)
    stats = from_sites(live_summaries(spark, path, snapshot), counted_pairs(fr))
    return Store(layout.read(spark, path, buckets, snapshot), fr, placement, stats, path, buckets, snapshot)


def write_summaries(triples: DataFrame, path: str, version: int) -> None:
    """Summaries by (site, fragment, property) of one version's partitions, kept beside them."""
    site_summaries(triples.where(F.col("ver") == version), layout.PARTS).coalesce(1).write.mode("overwrite").parquet(f"{path}/_summaries/{version}")


def live_summaries(spark: SparkSession, path: str, snapshot: layout.Snapshot) -> DataFrame:
    """The kept summaries of the partitions a snapshot consists of; no triple is read."""
    kept = [f"{path}/_summaries/{v}" for v in sorted({v for v, _, _ in snapshot.live})]
    return spark.read.parquet(*kept).where(layout.live_in(snapshot)) if kept else site_summaries(spark.createDataFrame([], layout.SCHEMA), layout.PARTS)


def virtual_store(triples: DataFrame, fr: Fragmentation, placement: Placement) -> Store:
    """A store whose sites are computed, not written; for planning and small data."""
    return Store(place_triples(triples, fr, placement), fr, placement, statistics(triples, fr))


def save_catalogue(store: Store, path: str) -> None:
    """Fragment definitions, sizes, sites and statistics as JSON, through Spark's file systems."""
    fr, p = store.fragmentation, store.placement
    body = {
        "path": store.path,
        "buckets": store.buckets,
        "predicates": [[x.component, x.op, x.value, x.kind] for x in fr.predicates],
        "fragments": [{"number": f.number, "bits": f.bits, "size": f.size, "freq": f.freq, "remainder": f.remainder, "cells": f.cells} for f in fr.fragments],
        "cell_sizes": [[*c, n] for c, n in fr.cell_size.items()],
        "candidates": [[x.component, x.op, x.value, x.kind] for x in fr.cells.predicates],
        "sites": p.n,
        "site_of": p.site_of,
        "split": sorted(p.split),
        "copies": {k: sorted(v) for k, v in p.copies.items()},
        "state": [[s.number, s.capacity if s.capacity != float("inf") else None, s.fragments, s.load, s.used] for s in p.sites],
        "uniform": p.uniform,
        "total": store.stats.total,
        "subjects": store.stats.subjects,
        "objects": store.stats.objects,
        "properties": {k: [v.rows, v.subjects, v.objects, v.low, v.high] for k, v in store.stats.properties.items()},
        "pairs": [[*k, n] for k, n in store.stats.pairs.items()],
    }
    write_text(SparkSession.active(), path, json.dumps(body))


def load_catalogue(path: str) -> dict:
    if (text := read_text(SparkSession.active(), path)) is None:
        raise FileNotFoundError(path)
    return json.loads(text)


def open_store(spark: SparkSession, catalogue: str, analysis: Analysis) -> Store:
    """A written store as its catalogue describes it: nothing is counted or placed again. ``analysis`` is that of the load,
    whose patterns new fragment edges would be weighed by."""
    c = load_catalogue(catalogue)
    ps, candidates = ([Predicate(*x) for x in c[k]] for k in ("predicates", "candidates"))
    fragments = []
    for f in c["fragments"]:
        signs = [bool(f["bits"] >> i & 1) for i in range(len(ps))]
        pos, neg = (tuple(p for p, yes in zip(ps, signs, strict=True) if yes is w) for w in (True, False))
        fragments.append(Fragment(f["number"], f["bits"], pos, neg, f["size"], f["freq"], f["remainder"], [tuple(x) for x in f["cells"]]))
    sizes = {tuple(x[:3]): x[3] for x in c["cell_sizes"]}
    fr = Fragmentation(ps, Cells(candidates), fragments, analysis, {x: f.number for f in fragments for x in f.cells}, len(candidates), sizes)
    sites = [Site(n, float("inf") if cap is None else cap, fs, load, used) for n, cap, fs, load, used in c["state"]]
    placement = Placement(c["sites"], {int(k): v for k, v in c["site_of"].items()}, sites, set(c["split"]), c["uniform"], [], {int(k): set(v) for k, v in c["copies"].items()})
    stats = Statistics(c["total"], {k: PropertyStats(*v) for k, v in c["properties"].items()}, {tuple(x[:3]): x[3] for x in c["pairs"]}, c["subjects"], c["objects"])
    snapshot = layout.newest(spark, c["path"])
    return Store(layout.read(spark, c["path"], c["buckets"], snapshot), fr, placement, stats, c["path"], c["buckets"], snapshot)
