"""By-property baseline: a fragment for each property that the load uses, placed by load balance alone."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from loadshard.operators.allocation import place
from loadshard.operators.fragments import fragment
from loadshard.operators.predicates import Predicate, extract
from loadshard.operators.store import Store, bootstrap, virtual_store
from loadshard.workload.load import Analysis


def cuts_of(a: Analysis, cuts: str = "properties") -> list[Predicate]:
    return [p for p in extract(a) if cuts == "simple_predicates" or p.component == "p" and p.op == "="]


def build(spark: SparkSession, triples: DataFrame, a: Analysis, n: int, cuts: str = "properties", form: str = "balance", path: str | None = None) -> Store:
    """cuts: properties (constants ignored) or simple_predicates (kept); form: balance or round_robin. Properties that
    the load never names are the remainder, dealt by a hash."""
    fr = fragment(a, triples, cuts_of(a, cuts), signature="none")
    p = place(fr, n, form)
    return bootstrap(spark, triples, fr, p, path) if path else virtual_store(triples, fr, p)
