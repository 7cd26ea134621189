"""How a store lies on disk: versions of (site, fragment) partitions, switched by a manifest, bucketed by subject.

Data go to ``<path>/ver=<version>/site_id=/frag_id=``. A manifest names the partitions of which the store consists and the
batches they hold; it is written under a new name once all data are there, so a failed writer leaves the former store whole."""

from __future__ import annotations

import hashlib
import json
from dataclasses import dataclass
from math import ceil

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.functions.shared import delete_path, list_names, read_text, write_text

COLUMNS = ("s", "p", "o", "o_kind", "o_num", "site_id", "frag_id")
SCHEMA = "s string, p string, o string, o_kind string, o_num double, ver int, site_id int, frag_id int"
PARTS = ("ver", "site_id", "frag_id")
BUCKET_ROWS, MOST_BUCKETS = 1_000_000, 4096


@dataclass(frozen=True)
class Snapshot:
    """The partitions (version, site, fragment) a store consists of, and the batches applied so far."""

    version: int
    live: frozenset[tuple[int, int, int]]
    batches: tuple[int, ...] = ()


def bucket_count(largest: int, rows: int = BUCKET_ROWS) -> int:
    """Buckets for a largest fragment of so many triples: a power of two, at most 4096."""
    return min(MOST_BUCKETS, 1 << max(0, ceil(largest / rows) - 1).bit_length())


def evenly_bucketed(triples: DataFrame, buckets: int, tolerance: float = 4.0) -> bool:
    """Whether no bucket holds more than ``tolerance`` times the mean: a subject with a large share of all triples would
    make one task of each join, which only a layout without buckets lets Spark split."""
    if buckets < 2:
        return True
    got = triples.groupBy(F.pmod(F.hash("s"), F.lit(buckets)).alias("b")).count().agg(F.max("count"), F.sum("count")).first()
    return not got[1] or got[0] <= tolerance * got[1] / buckets


def table_name(path: str) -> str:
    return f"loadshard_{hashlib.sha1(path.rstrip('/').encode()).hexdigest()[:20]}"


def write(rows: DataFrame, path: str, version: int, buckets: int, first: bool = False, more: bool = False) -> None:
    """Adds one version's partitions. ``first`` starts the store anew at this path, ``more`` goes on with a version."""
    spark = rows.sparkSession
    if first:
        for names in ("_manifest", "_summaries"):
            delete_path(spark, f"{path}/{names}")
    out = rows.withColumn("ver", F.lit(version)).select(*COLUMNS[:5], *PARTS)
    if not first and not more:
        forget(spark, path, [f"ver={version}"])  # of a writer that failed before its manifest
    if not buckets:
        out.write.mode("overwrite" if first else "append").partitionBy(*PARTS).parquet(path)
    elif first:
        out.write.mode("overwrite").partitionBy(*PARTS).bucketBy(buckets, "s").sortBy("p", "o", "s").option("path", path).format("parquet").saveAsTable(table_name(path))
    else:
        table(spark, path, buckets)
        out.write.mode("append").insertInto(table_name(path))


def table(spark: SparkSession, path: str, buckets: int) -> DataFrame:
    """The bucketed files as a table of the session, made known to it where they are not."""
    name = table_name(path)
    if not spark.catalog.tableExists(name):
        where = path.replace("'", "\\'")
        spark.sql(f"CREATE TABLE {name} ({SCHEMA}) USING parquet PARTITIONED BY ({', '.join(PARTS)}) CLUSTERED BY (s) SORTED BY (p, o, s) INTO {buckets} BUCKETS LOCATION '{where}'")
        spark.sql(f"ALTER TABLE {name} RECOVER PARTITIONS")
    return spark.table(name)


def read(spark: SparkSession, path: str, buckets: int, snapshot: Snapshot) -> DataFrame:
    """The snapshot's triples. Which partitions count is a filter on partition columns alone, so others are never opened."""
    rows = table(spark, path, buckets) if buckets else spark.read.schema(SCHEMA).parquet(path)
    return rows.where(live_in(snapshot)).select(*COLUMNS)


def live_in(snapshot: Snapshot) -> Column:
    versions = {v for v, _, _ in snapshot.live}
    if len(versions) == 1 and versions == {snapshot.version}:  # written whole
        return F.col("ver") == snapshot.version
    return F.concat_ws("/", *PARTS).isin([f"{v}/{a}/{b}" for v, a, b in sorted(snapshot.live)])


def parts_of_version(spark: SparkSession, path: str, version: int) -> frozenset[tuple[int, int, int]]:
    """The partitions that a version's folder holds; they are listed, not read."""
    number = lambda name: int(name.split("=")[1])
    sites = [x for x in list_names(spark, f"{path}/ver={version}") if x.startswith("site_id=")]
    return frozenset((version, number(a), number(b)) for a in sites for b in list_names(spark, f"{path}/ver={version}/{a}") if b.startswith("frag_id="))


def commit(spark: SparkSession, path: str, snapshot: Snapshot) -> None:
    """Makes a snapshot the store. Partitions that neither it nor the one before consists of are deleted afterwards."""
    before = newest(spark, path)
    write_text(spark, f"{path}/_manifest/{snapshot.version:012d}.json", json.dumps({"version": snapshot.version, "live": sorted(snapshot.live), "batches": list(snapshot.batches)}))
    older = [n for n in list_names(spark, f"{path}/_manifest") if n.endswith(".json") and int(n[:-5]) < (before.version if before else 0)]
    for n in older:
        gone = _snapshot(read_text(spark, f"{path}/_manifest/{n}")).live - before.live - snapshot.live
        forget(spark, path, [f"ver={v}/site_id={a}/frag_id={b}" for v, a, b in sorted(gone)])
        delete_path(spark, f"{path}/_manifest/{n}")
        for v in {v for v, _, _ in gone} - {v for v, _, _ in before.live | snapshot.live}:
            delete_path(spark, f"{path}/_summaries/{v}")


def newest(spark: SparkSession, path: str) -> Snapshot | None:
    names = sorted(n for n in list_names(spark, f"{path}/_manifest") if n.endswith(".json"))
    return _snapshot(read_text(spark, f"{path}/_manifest/{names[-1]}")) if names else None


def _snapshot(text: str) -> Snapshot:
    c = json.loads(text)
    return Snapshot(c["version"], frozenset(map(tuple, c["live"])), tuple(c["batches"]))


def forget(spark: SparkSession, path: str, parts: list[str]) -> None:
    """Deletes partitions, in the session's table as well as on disk."""
    for part in parts:
        delete_path(spark, f"{path}/{part}")
        try:
            spark.sql(f"ALTER TABLE {table_name(path)} DROP IF EXISTS PARTITION ({part.replace('/', ', ')})")
        except AnalysisException:
            pass  # no such table: a store without buckets, or one that this session has not opened
