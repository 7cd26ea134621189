"""Cutting lineage through the folder that executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a folder of our own only where that is unset on a local master."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("loadshard.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="loadshard-")
        spark.conf.set("loadshard.checkpoint.dir", found)
    return found


def fresh_path(spark: SparkSession, label: str = "table") -> str:
    return f"{shared_dir(spark).rstrip('/')}/loadshard-{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame) -> DataFrame:
    path = fresh_path(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _file(spark: SparkSession, path: str) -> tuple:
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    return jpath.getFileSystem(spark._jsc.hadoopConfiguration()), jpath


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """A small file on whatever file system the path names, there as a whole or not at all; a former one is replaced."""
    fs, at = _file(spark, path)
    _, made = _file(spark, f"{path}.{uuid.uuid4().hex}.tmp")
    out = fs.create(made, True)
    try:
        out.write(bytearray(text.encode()))
    finally:
        out.close()
    if fs.exists(at):
        fs.delete(at, False)
    if not fs.rename(made, at):
        raise OSError(f"cannot write {path}")


def list_names(spark: SparkSession, path: str) -> list[str]:
    fs, at = _file(spark, path)
    return sorted(x.getPath().getName() for x in fs.listStatus(at)) if fs.exists(at) else []


def delete_path(spark: SparkSession, path: str) -> None:
    fs, at = _file(spark, path)
    fs.delete(at, True)


def read_text(spark: SparkSession, path: str) -> str | None:
    """The text of a small file; None where there is none."""
    fs, at = _file(spark, path)
    if not fs.exists(at):
        return None
    source = fs.open(at)
    try:
        return bytes(spark._jvm.org.apache.commons.io.IOUtils.toByteArray(source)).decode()
    finally:
        source.close()
