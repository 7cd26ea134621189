"""Query loads as relations, and what the partitioner learns from them.

The relational form has a row for each triple pattern of each query: query_id, weight, bgp_id, pattern_id, optional,
s, p, o, o_kind (null where a variable stands) and s_var, p_var, o_var. All analyses are joins and partial
aggregations over it, so that long logs need no driver loop."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.query.ast import Query, Term, TriplePattern, Var
from loadshard.query.parser import parse

SCHEMA = "query_id string, weight long, bgp_id int, pattern_id int, optional boolean, s string, p string, o string, o_kind string, s_var string, p_var string, o_var string"
KEY = ("s", "p", "o", "o_kind")


def pattern_rows(q: Query, weight: int) -> list[tuple]:
    out = []
    for b, g in enumerate(q.branches):
        every = [(t, False) for t in g.required] + [(t, True) for part in g.optional for t in part]
        for i, (t, opt) in enumerate(every):
            text = [x.text if isinstance(x, Term) else None for _, x in t.parts()]
            var = [x.name if isinstance(x, Var) else None for _, x in t.parts()]
            out.append((q.qid, weight, b, i, opt, *text, t.o.kind if isinstance(t.o, Term) else None, *var))
    return out


@dataclass
class QueryLoad:
    queries: list[Query]
    weights: dict[str, int]
    rows: DataFrame = field(repr=False)


def load_queries(spark: SparkSession, items: list[tuple[str, str, int]]) -> QueryLoad:
    """A load of (query id, text, weight)."""
    queries = [parse(text, qid) for qid, text, _ in items]
    weights = {qid: w for qid, _, w in items}
    return QueryLoad(queries, weights, spark.createDataFrame([r for q in queries for r in pattern_rows(q, weights[q.qid])], SCHEMA))


def collapse_duplicates(log: DataFrame, text_col: str = "text") -> DataFrame:
    """(query_id, text, weight) of a log with repeats; ids are hashes of the texts."""
    text = F.regexp_replace(F.trim(text_col), r"\s+", " ")
    return log.select(text.alias("text")).groupBy("text").agg(F.count(F.lit(1)).alias("weight")).select(F.md5("text").alias("query_id"), "text", "weight")


def parse_log(log: DataFrame) -> DataFrame:
    """The relational form of (query_id, text, weight), parsed by the executors; unreadable texts give no rows."""

    def parsed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        for b in batches:
            rows = []
            for qid, text, w in zip(b["query_id"], b["text"], b["weight"], strict=True):
                try:
                    rows += pattern_rows(parse(text, qid), int(w))
                except ValueError:
                    continue
            yield pd.DataFrame(rows, columns=names)

    return log.select("query_id", "text", "weight").mapInPandas(parsed, SCHEMA)


def term_frequency(rows: DataFrame) -> DataFrame:
    """(term, kind, freq): weight of the queries that have a constant at subject or object position."""
    both = F.array(F.struct(F.col("s").alias("term"), F.lit("iri").alias("kind")), F.struct(F.col("o").alias("term"), F.col("o_kind").alias("kind")))
    terms = rows.select("query_id", "weight", F.explode(both).alias("x")).select("query_id", "weight", "x.*").where("term is not null").distinct()
    return terms.groupBy("term", "kind").agg(F.sum("weight").alias("freq"))


def normalize(rows: DataFrame, theta: int) -> DataFrame:
    """Constants of subject and object in fewer than ``theta`` queries become variables; properties never do."""
    kept = F.broadcast(term_frequency(rows).where(F.col("freq") >= theta))
    s, o = (kept.select(F.col("term").alias(f"{c}_"), F.col("kind").alias(f"{c}k_")) for c in "so")
    joined = rows.join(s, (F.col("s") == F.col("s_")) & (F.col("sk_") == "iri"), "left").join(o, (F.col("o") == F.col("o_")) & (F.col("o_kind") == F.col("ok_")), "left")
    return joined.withColumns({"s": F.col("s_"), "o": F.col("o_"), "o_kind": F.col("ok_")}).select(*rows.columns)


def anonymize(rows: DataFrame) -> DataFrame:
    """(query_id, weight, bgp_id, pattern_id, s, p, o, o_kind, pattern): one null stands for every variable."""
    key = F.concat_ws(" ", *(F.coalesce(c, F.lit("_")) for c in ("s", "p", "o")), F.coalesce("o_kind", F.lit("_")))
    return rows.select("query_id", "weight", "bgp_id", "pattern_id", *KEY, key.alias("pattern"), "s_var", "p_var", "o_var")


def phi(rows: DataFrame, theta: int) -> DataFrame:
    """The distinct anonymised, normalised patterns."""
    return anonymize(normalize(rows, theta)).select("pattern", *KEY).distinct()


def pattern_frequency(rows: DataFrame, theta: int) -> DataFrame:
    """(pattern, s, p, o, o_kind, freq): weight of the queries that contain a pattern, each counted once."""
    once = anonymize(normalize(rows, theta)).select("query_id", "weight", "pattern", *KEY).distinct()
    return once.groupBy("pattern", *KEY).agg(F.sum("weight").alias("freq"))


def pattern_witnesses(rows: DataFrame, theta: int) -> DataFrame:
    """(query_id, weight, a, b) with a <= b: pairs of patterns that share a variable in a query, once a query."""
    occ = anonymize(normalize(rows, theta))
    seats = occ.select("query_id", "weight", "bgp_id", "pattern_id", "pattern", F.explode(F.array_distinct(F.array_compact(F.array("s_var", "p_var", "o_var")))).alias("v"))
    x = seats.select("query_id", "weight", "bgp_id", "v", F.col("pattern_id").alias("i"), F.col("pattern").alias("x"))
    y = seats.select("query_id", "bgp_id", "v", F.col("pattern_id").alias("j"), F.col("pattern").alias("y"))
    pairs = x.join(y, ["query_id", "bgp_id", "v"]).where("i < j")
    return pairs.select("query_id", "weight", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def pattern_edges(rows: DataFrame, theta: int) -> DataFrame:
    """(a, b, w): edges of the global query graph; a pattern that joins itself has a self-loop."""
    return pattern_witnesses(rows, theta).groupBy("a", "b").agg(F.sum("weight").alias("w"))


def drift(log: DataFrame, window: str = "1 day") -> DataFrame:
    """(window, term, freq, share): constants' shares of the queries over time, from (ts, query_id, term, weight)."""
    by = log.groupBy(F.window("ts", window).alias("window"), "term").agg(F.sum("weight").alias("freq"))
    return by.withColumn("share", F.col("freq") / F.sum("freq").over(W.partitionBy("window")))


@dataclass(frozen=True)
class Pattern:
    """An anonymised pattern on the driver; null components are variables."""

    key: str
    s: str | None
    p: str | None
    o: str | None
    o_kind: str | None
    freq: int

    def constants(self) -> list[tuple[str, str, str]]:
        """(component, text, kind)."""
        return [(c, v, k) for c, v, k in (("s", self.s, "iri"), ("p", self.p, "iri"), ("o", self.o, self.o_kind)) if v is not None]


@dataclass
class Analysis:
    """What the driver keeps of a load: of the size of its distinct patterns, whatever the log's length."""

    patterns: dict[str, Pattern]
    edges: list[tuple[str, str, int]]
    occurrences: dict[str, set[str]]  # pattern -> queries
    witnesses: dict[tuple[str, str], set[str]]
    weights: dict[str, int]
    queries: list[Query]


def analyse(load: QueryLoad, theta: int) -> Analysis:
    patterns = {r["pattern"]: Pattern(r["pattern"], r["s"], r["p"], r["o"], r["o_kind"], r["freq"]) for r in pattern_frequency(load.rows, theta).collect()}
    occ: dict[str, set[str]] = {}
    for r in anonymize(normalize(load.rows, theta)).select("pattern", "query_id").distinct().collect():
        occ.setdefault(r[0], set()).add(r[1])
    wit: dict[tuple[str, str], set[str]] = {}
    for r in pattern_witnesses(load.rows, theta).collect():
        wit.setdefault((r["a"], r["b"]), set()).add(r["query_id"])
    edges = sorted((a, b, sum(load.weights[q] for q in qs)) for (a, b), qs in wit.items())
    return Analysis(patterns, edges, occ, wit, load.weights, load.queries)


def filters_of(q: Query, t: TriplePattern) -> list[tuple[str, str, Term]]:
    """(component, op, constant) of conjunctive comparisons that bind a variable of a pattern to constants."""
    out = []
    for g in q.branches:
        if t not in g.required and not any(t in part for part in g.optional):
            continue
        stack = list(g.filters)
        while stack:
            f = stack.pop()
            if f.op == "&&":
                stack += f.args
                continue
            turn = {"<": ">", "<=": ">=", ">": "<", ">=": "<="}
            for c, x in t.parts():
                if not isinstance(x, Var):
                    continue
                if f.op in ("<", "<=", "=", ">=", ">"):
                    a, b = f.args
                    if a == x and isinstance(b, Term):
                        out.append((c, f.op, b))
                    elif b == x and isinstance(a, Term):
                        out.append((c, turn.get(f.op, f.op), a))
                elif f.op in ("isIRI", "isLiteral", "isNumeric", "regex", "contains", "strstarts") and f.args[0] == x:
                    out.append((c, f.op, f.args[1] if len(f.args) > 1 else Term("", "str")))
    return out
