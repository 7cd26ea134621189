"""Central baseline: one relation, the initial plan only, no fragments or sites."""

from __future__ import annotations

from pyspark.sql import DataFrame

from loadshard.query.ast import Query
from loadshard.query.compile import to_dataframe


def run(q: Query, triples: DataFrame) -> DataFrame:
    return to_dataframe(q, triples)
