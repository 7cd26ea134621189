"""Global dictionary of terms: serial numbering by order, or hash-split numbering, and encoding by one join."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.functions.shared import materialize


def terms(triples: DataFrame) -> DataFrame:
    """(term, kind) of all components, distinct after map-side combination."""
    iri = F.lit("iri")
    each = F.array(F.struct(F.col("s").alias("term"), iri.alias("kind")), F.struct(F.col("p").alias("term"), iri.alias("kind")), F.struct(F.col("o").alias("term"), F.col("o_kind").alias("kind")))
    return triples.select(F.explode(each).alias("x")).select("x.*").distinct()


def _numbered(rows: DataFrame, part: str, order: list[str]) -> DataFrame:
    """ids 1.. by part and order: counts of parts (few) give offsets, windows stay within parts."""
    rows = materialize(rows)
    counts = rows.groupBy(part).agg(F.count(F.lit(1)).alias("n"))
    offsets = counts.select(part, (F.sum("n").over(W.orderBy(part)) - F.col("n")).alias("offset"))
    rank = F.row_number().over(W.partitionBy(part).orderBy(*order))
    return rows.withColumn("r", rank).join(F.broadcast(offsets), part).select("term", "kind", (F.col("r") + F.col("offset")).cast("long").alias("id"))


def build(triples: DataFrame, parts: int = 32) -> DataFrame:
    """(term, kind, id): ids follow the order of (term, kind). Range parts by the terms' quantiles, then offsets; there
    is no window over all terms."""
    t = materialize(terms(triples))
    ranged = t.repartitionByRange(parts, "term", "kind").withColumn("part", F.spark_partition_id())
    return _numbered(ranged, "part", ["term", "kind"])


def build_parallel(triples: DataFrame, parts: int = 32) -> DataFrame:
    """(term, kind, id): each hash part has its own dictionary, made global by the parts' offsets."""
    return _numbered(terms(triples).withColumn("part", F.pmod(F.xxhash64("term", "kind"), F.lit(parts))), "part", ["term", "kind"])


def encode(triples: DataFrame, dictionary: DataFrame) -> DataFrame:
    """triples with s_id, p_id, o_id: components are unpivoted, so the dictionary is joined once."""
    iri = F.lit("iri")
    each = F.array(
        F.struct(F.lit("s").alias("c"), F.col("s").alias("term"), iri.alias("kind")), F.struct(F.lit("p").alias("c"), F.col("p").alias("term"), iri.alias("kind")), F.struct(F.lit("o").alias("c"), F.col("o").alias("term"), F.col("o_kind").alias("kind"))
    )
    key = ["s", "p", "o", "o_kind", "o_num"]
    long = triples.select(*key, F.explode(each).alias("x")).select(*key, "x.c", "x.term", "x.kind").join(dictionary, ["term", "kind"])
    pick = lambda c: F.max(F.when(F.col("c") == c, F.col("id"))).alias(f"{c}_id")
    return long.groupBy(*key).agg(pick("s"), pick("p"), pick("o"))


def decode(rows: DataFrame, dictionary: DataFrame, columns: list[str]) -> DataFrame:
    """rows with each id column replaced by its term."""
    for c in columns:
        d = dictionary.select(F.col("id").alias(c), F.col("term").alias(f"{c}__t"))
        rows = rows.join(d, c, "left").drop(c).withColumnRenamed(f"{c}__t", c)
    return rows
