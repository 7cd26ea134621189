from __future__ import annotations

import pytest

from loadshard import queries
from loadshard.queries import QUERIES
from loadshard.query.compile import to_dataframe
from loadshard.query.parser import parse
from loadshard.sources.mapping import subjects_repeat, triple_view, triples
from loadshard.workload.generator import random_queries, split
from loadshard.workload.measures import response_times, throughput
from tests.conftest import rows_of


def test_random_queries_are_never_empty(spark, sf):
    t = triples(spark, sf, ("nation", "customer", "orders")).cache()
    load = random_queries(t, 6, seed=3)
    assert len({q for q, _, _ in load}) == 6 and load == random_queries(t, 6, seed=3)
    for _, text, _ in load:
        q = parse(text)
        assert 1 <= len(q.branches[0].required) <= 6 and to_dataframe(q, t).count() > 0
    a, b = split(load)
    assert len(a) == len(b) == 3 and sorted(a + b) == sorted(load)
    t.unpersist()


def test_measures(spark):
    run = lambda q: spark.range(int(q))
    assert set(response_times(run, ["1", "2"], 1)) == {"1", "2"}
    got = throughput(run, ["1", "2"], 2, interval=0.1)
    assert got.completed == 4 and got.timed_out == 0 and got.per_minute > 0


@pytest.mark.parametrize("name", ["access_paths", "khop_local_queries", "simple_predicates", "allocation_damped", "benefit_trace_literal", "fragment_edges_query_count", "fragment_frequency_pattern_sum"])
def test_each_run_reads_given_tables(spark, sf, name):
    sc = spark.sparkContext._jsc.sc()

    def read():
        sc.listenerBus().waitUntilEmpty(30_000)
        return sc.statusStore().executorSummary("driver").totalInputBytes()

    for _ in range(2):  # nothing kept from an earlier run stands for the tables
        before = read()
        QUERIES[name](spark, sf).collect()
        assert read() > before


def test_central_reads_a_view_without_writing(spark, sf, monkeypatch, tmp_path):
    def no(*_):
        raise AssertionError("central writes nothing")

    monkeypatch.setattr(queries, "written", no)
    assert QUERIES["central_b07"](spark, sf).count() >= 0
    rows = spark.read.parquet(f"{sf}/lineitem.parquet").limit(50)
    for name, df in (("once", rows), ("twice", rows.union(rows))):
        df.write.parquet(f"{tmp_path}/{name}/lineitem.parquet")
    assert not subjects_repeat(spark, f"{tmp_path}/once", "lineitem") and subjects_repeat(spark, f"{tmp_path}/twice", "lineitem")
    view = lambda name, unique=(): rows_of(triple_view(spark, f"{tmp_path}/{name}", ("lineitem",), unique=unique))
    assert view("once", ("lineitem",)) == view("once") == view("twice") == rows_of(triples(spark, f"{tmp_path}/twice", ("lineitem",)))


def test_stores_write_no_triples(spark, sf, monkeypatch):
    from loadshard import queries

    def no(*_):
        raise AssertionError("triples were written")

    monkeypatch.setattr(queries, "written", no)
    monkeypatch.setattr(queries, "_held", {})
    assert queries.QUERIES["b01"](spark, sf).count()
    assert queries.QUERIES["byprop_b01"](spark, sf).count()
