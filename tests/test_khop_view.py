from __future__ import annotations

import pytest

from loadshard import queries
from loadshard.baselines import khop
from loadshard.oracles import of_query
from loadshard.sources.mapping import triples
from loadshard.workload.catalogue import query
from tests.conftest import rows_of, rows_of_sql

ASKED = ("b01", "b05", "b08", "b10", "b12", "b16", "s6")


@pytest.fixture(scope="module")
def plain(spark, sf):
    return khop.build(triples(spark, sf), queries.SITES)


def test_view_has_the_parts_and_copies_of_written_triples(spark, sf, plain):
    view = queries.built_khop(spark, sf)
    assert rows_of(view.labels) == rows_of(plain.labels)
    assert rows_of(view.triples) == rows_of(plain.triples)
    want = plain.triples.selectExpr("part_id", "cast(owned as long) as o").groupBy("part_id").agg({"*": "count", "o": "sum"})
    assert sorted(map(tuple, queries.QUERIES["khop_parts"](spark, sf).collect())) == sorted(map(tuple, want.collect()))


def test_nothing_but_hubs_is_written(spark, sf):
    view = queries.built_khop(spark, sf)
    assert view.kept.count() == sum(view.table(m).count() for m in view.hubs)


def test_edges_are_read_both_ways(spark):
    t = spark.createDataFrame([(s, "p:x", o, "iri", None) for s, o in (("a", "h"), ("b", "h"), ("h", "z"))], "s string, p string, o string, o_kind string, o_num double")
    e = khop.entity_edges(t)
    assert e.columns == ["a", "b"] and sorted(map(tuple, e.collect())) == [("a", "h"), ("b", "h")]


@pytest.mark.parametrize("name", ASKED)
def test_answers_and_duplicates(spark, sf, duck, plain, name):
    view = queries.built_khop(spark, sf)
    want = rows_of_sql(duck, of_query(name))
    assert rows_of(khop.run(query(name), view)) == want
    assert rows_of(khop.duplicates(query(name), view)) == rows_of(khop.duplicates(query(name), plain))


@pytest.mark.parametrize("name", ["b07", "b05"])
def test_lines_and_distinct_answers(spark, sf, duck, name):
    assert rows_of(khop.run(query(name), queries.built_khop(spark, sf), "distinct")) == rows_of_sql(duck, of_query(name))
