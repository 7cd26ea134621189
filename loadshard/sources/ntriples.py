"""N-Triples text as a source and a sink, and CSV of triples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LINE = r"^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|\"((?:[^\"\\]|\\.)*)\"(?:\^\^<([^>]*)>|@[A-Za-z-]+)?)\s*\.\s*$"
NUMBER, TIME = "http://www.w3.org/2001/XMLSchema#decimal", "http://www.w3.org/2001/XMLSchema#long"
NUMBERS = tuple(f"http://www.w3.org/2001/XMLSchema#{t}" for t in ("decimal", "integer", "int", "double", "float"))


def _unescaped(c: Column) -> Column:
    c = F.replace(F.replace(F.replace(F.replace(c, F.lit("\\\\"), F.lit("\x00")), F.lit('\\"'), F.lit('"')), F.lit("\\n"), F.lit("\n")), F.lit("\\r"), F.lit("\r"))
    return F.replace(c, F.lit("\x00"), F.lit("\\"))


def _escaped(c: Column) -> Column:
    return F.replace(F.replace(F.replace(F.replace(c, F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"')), F.lit("\n"), F.lit("\\n")), F.lit("\r"), F.lit("\\r"))


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Triples of a text of one statement a line; lines that are no statement (comments, blanks) are left out."""
    raw = spark.read.text(path).where(F.col("value").rlike(LINE))
    g = lambda i: F.regexp_extract("value", LINE, i)
    kind = F.when(F.col("value").rlike(r"^\s*<[^>]*>\s+<[^>]*>\s+<"), "iri").when(g(5).isin(*NUMBERS), "num").when(g(5) == TIME, "ts").otherwise("str")
    o = F.when(kind == "iri", g(3)).otherwise(_unescaped(g(4)))
    return raw.select(g(1).alias("s"), g(2).alias("p"), o.alias("o"), kind.alias("o_kind"), F.when(kind.isin("num", "ts"), o.try_cast("double")).alias("o_num"))


def write_ntriples(triples: DataFrame, path: str) -> None:
    datatype = F.when(F.col("o_kind") == "num", F.lit(f"^^<{NUMBER}>")).when(F.col("o_kind") == "ts", F.lit(f"^^<{TIME}>")).otherwise("")
    o = F.when(F.col("o_kind") == "iri", F.concat(F.lit("<"), F.col("o"), F.lit(">"))).otherwise(F.concat(F.lit('"'), _escaped(F.col("o")), F.lit('"'), datatype))
    triples.select(F.concat(F.lit("<"), F.col("s"), F.lit("> <"), F.col("p"), F.lit("> "), o, F.lit(" .")).alias("value")).write.text(path)


def write_csv(triples: DataFrame, path: str) -> None:
    triples.write.option("header", True).csv(path)


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("s string, p string, o string, o_kind string, o_num double").option("header", True).csv(path)
