"""The given tables as one relation of triples (s, p, o, o_kind, o_num)."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TYPE = "rdf:type"
COLUMNS = ("s", "p", "o", "o_kind", "o_num")


@dataclass(frozen=True)
class TableMap:
    """How rows of a table become triples: ``subject`` is a prefix and its key columns, ``links`` are columns that name
    other subjects by a prefix, ``literals`` are columns with their kind (int, num, str, ts, long)."""

    name: str
    prefix: str
    key: tuple[str, ...]
    cls: str | None
    links: tuple[tuple[str, str], ...]
    literals: tuple[tuple[str, str], ...]


def _lits(kind: str, *names: str) -> tuple[tuple[str, str], ...]:
    return tuple((n, kind) for n in names)


MAPS = (
    TableMap("region", "region", ("r_regionkey",), "region", (), _lits("str", "r_name")),
    TableMap("nation", "nation", ("n_nationkey",), "nation", (("n_regionkey", "region"),), _lits("str", "n_name")),
    TableMap("customer", "customer", ("c_custkey",), "customer", (("c_nationkey", "nation"),), (*_lits("str", "c_name", "c_mktsegment"), *_lits("num", "c_acctbal"))),
    TableMap("supplier", "supplier", ("s_suppkey",), "supplier", (("s_nationkey", "nation"),), (*_lits("str", "s_name"), *_lits("num", "s_acctbal"))),
    TableMap("part", "part", ("p_partkey",), "part", (), (*_lits("str", "p_name", "p_brand", "p_type"), *_lits("int", "p_size"), *_lits("num", "p_retailprice"))),
    TableMap("orders", "order", ("o_orderkey",), "order", (("o_custkey", "customer"),), (*_lits("str", "o_orderstatus", "o_orderpriority"), *_lits("num", "o_totalprice"), *_lits("ts", "o_orderdate"))),
    TableMap(
        "lineitem", "line", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), "line",
        (("l_orderkey", "order"), ("l_partkey", "part"), ("l_suppkey", "supplier")),
        (*_lits("int", "l_linenumber"), *_lits("num", "l_quantity", "l_extendedprice", "l_discount", "l_tax"), *_lits("str", "l_returnflag", "l_linestatus"), *_lits("ts", "l_shipdate")),
    ),
    TableMap("events", "event", ("event_id",), "event", (("user_id", "customer"),), (*_lits("ts", "ts"), *_lits("str", "event_type"), *_lits("num", "value"), *_lits("json", "k"))),
    TableMap("documents", "doc", ("doc_id",), "document", (("source", "source"),), (*_lits("str", "lang"), *_lits("int", "n_chars"), *_lits("long", "text"))),
    TableMap("labels", "doc", ("doc_id",), None, (), _lits("int", "quality", "toxic")),
    TableMap("pages", "page", ("page_id",), "page", (), (*_lits("str", "url"), *_lits("long", "html"))),
    TableMap("benchmark", "bench", ("item_id",), "benchmark", (), _lits("long", "text")),
    TableMap("conversations", "turn", ("conv_id", "turn"), "turn", (("conv_id", "conv"),), (*_lits("int", "turn"), *_lits("str", "role"), *_lits("long", "text"))),
    TableMap("embeddings", "vec", ("vec_id",), "vector", (), _lits("int", "label")),
)
BY_NAME = {m.name: m for m in MAPS}


def prop(column: str) -> str:
    return f"p:{column}"


def _term(prefix: str, columns: tuple[str, ...]) -> Column:
    return F.concat(F.lit(f"{prefix}:"), F.concat_ws("/", *(F.col(c).cast("string") for c in columns)))


def subject_of(m: TableMap) -> Column:
    return _term(m.prefix, m.key)


def _literal(column: str, kind: str, long_text: bool) -> tuple[Column, str, Column]:
    """(text, kind, number) of a literal; numbers have a canonical text, times are epoch microseconds."""
    c, none = F.col(column), F.lit(None).cast("double")
    if kind == "json":
        c = F.get_json_object("props", f"$.{column}").cast("long")
    if kind in ("int", "json"):
        return c.cast("long").cast("string"), "num", c.cast("double")
    if kind == "num":
        return c.cast("decimal(18,2)").cast("string"), "num", c.cast("decimal(18,2)").cast("double")
    if kind == "ts":
        us = F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', {column})")
        return us.cast("string"), "ts", us.cast("double")
    return (c if kind == "str" or long_text else F.md5(c)), "str", none


def branches(m: TableMap, long_text: bool = False) -> list[tuple[str, Column, str, Column]]:
    """(property, object, kind, number) of each property of a table."""
    none = F.lit(None).cast("double")
    out = [(TYPE, F.lit(f"class:{m.cls}"), "iri", none)] if m.cls else []
    out += [(prop(c), _term(p, (c,)), "iri", none) for c, p in m.links]
    return out + [(prop(c), *_literal(c, k, long_text)) for c, k in m.literals]


def table_triples(df: DataFrame, m: TableMap, long_text: bool = False) -> DataFrame:
    """One scan of a table, each row unpivoted; null objects are absent triples."""
    rows = F.array(*(F.struct(F.lit(p).alias("p"), o.alias("o"), F.lit(k).alias("o_kind"), n.alias("o_num")) for p, o, k, n in branches(m, long_text)))
    return df.select(_term(m.prefix, m.key).alias("s"), F.explode(rows).alias("t")).select("s", "t.*").where("o is not null")


def triples(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] | None = None, long_text: bool = False) -> DataFrame:
    """The triple collection of the tables, without repeats."""
    maps = [m for m in MAPS if tables is None or m.name in tables]
    parts = [table_triples(spark.read.parquet(f"{sf_dir}/{m.name}.parquet"), m, long_text) for m in maps]
    return reduce(DataFrame.union, parts).dropDuplicates(["s", "p", "o", "o_kind"])


def subjects_repeat(spark: SparkSession, sf_dir: str, name: str) -> bool:
    """Whether two rows of a table may have one subject: only hashes of subjects are shuffled. Equal hashes of unlike
    subjects count as repeats, so a no is certain."""
    m, df = BY_NAME[name], spark.read.parquet(f"{sf_dir}/{name}.parquet")
    # hashes go to tasks of bounded size as they are, so that nothing is counted, and spilled, before or after
    tasks = max(1, df.count() // 500_000)
    return not df.select(F.xxhash64(_term(m.prefix, m.key)).alias("h")).repartition(tasks, "h").groupBy("h").count().where("count > 1").isEmpty()


def branch_view(df: DataFrame, m: TableMap, branch: tuple[str, Column, str, Column], unique: tuple[str, ...] = ()) -> DataFrame:
    p, o, k, n = branch
    b = df.select(_term(m.prefix, m.key).alias("s"), F.lit(p).alias("p"), o.alias("o"), F.lit(k).alias("o_kind"), n.alias("o_num")).where("o is not null")
    return b.distinct() if m.name == "lineitem" and m.name not in unique else b


def triple_view(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] | None = None, long_text: bool = False, unique: tuple[str, ...] = ()) -> DataFrame:
    """The same relation as a union of one-column scans with literal properties: a filter on p folds away all other
    branches, so a pattern with a constant property reads one column of one table. Repeats are kept out only where a
    table's key can repeat (lineitem), by a shuffle of each branch; ``unique`` names tables that need none, as their
    subjects were seen not to repeat (``subjects_repeat``)."""
    parts = []
    for m in MAPS:
        if tables is not None and m.name not in tables:
            continue
        df = spark.read.parquet(f"{sf_dir}/{m.name}.parquet")
        for p, o, k, n in branches(m, long_text):
            parts.append(branch_view(df, m, (p, o, k, n), unique))
    return reduce(DataFrame.union, parts)
