from __future__ import annotations

import pytest

from loadshard import queries
from loadshard.oracles import of_query
from loadshard.operators.fragments import fragment
from loadshard.operators.predicates import Cells
from loadshard.sources.mapping import triples
from loadshard.sources.placed import only_cell, parts, sampled_fragments
from tests.conftest import rows_of, rows_of_sql


def test_sizes_from_counts_and_one_scan_of_samples(spark, sf):
    st = queries.built(spark, sf)
    t, fr = triples(spark, sf).cache(), st.fragmentation
    sizes = lambda x: {f.label(): f.size for f in x.fragments}
    assert sizes(fragment(fr.analysis, t)) == sizes(fr)
    got = sampled_fragments(fr.analysis, parts(spark, sf, ("lineitem",)), fr.predicates, (0.05, 0.1), signature="none")
    for share, one in got.items():
        assert sizes(one) == sizes(fragment(fr.analysis, t, fr.predicates, signature="none", fraction=share))
    view = parts(spark, sf, ("lineitem",))
    free = [p for m, p, kind, _ in view if only_cell(Cells(fr.predicates), m, p, kind)]
    assert "p:l_orderkey" in free and "p:o_orderpriority" not in free
    t.unpersist()


@pytest.mark.parametrize("name", ["b07", "b08", "b09", "b18"])
def test_stars_are_one_scan(spark, sf, duck, name):
    joins = lambda df: df._jdf.queryExecution().optimizedPlan().toString().count("Join ")
    df = queries.QUERIES[name](spark, sf)
    lines = 0 if queries.known(spark, sf)["single"]("lineitem") else 2  # a star of lines only where no line repeats
    assert joins(df) == {"b07": 2 + lines, "b08": 1, "b09": 1, "b18": 0}[name]
    assert rows_of(df) == rows_of_sql(duck, of_query(name))
