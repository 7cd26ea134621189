"""Mixing sources to target weights, in DataFrame functions only.

Each source's documents are laid end to end in a keyed order and cut into blocks of ``block`` words. Output
shards draw their source counts from a multinomial; draws beyond a source's slots go to sources that lack some,
so that totals are exact. Slot i of a source takes block perm(i mod blocks) of pass i div blocks, where perm is a
keyed swap-or-not permutation of the block numbers; blocks and documents are then joined by block number.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.llm.common import WORD, materialize, running_total, table, unused

WEIGHTS = (5, 2, 1)
CELL_ROWS = 4_096
TASK_SLOTS, MAX_TASKS = 65_536, 100_000
GRID = 1 << 16


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = 1.5, passes: int = 2) -> DataFrame:
    """(sid, source, source_size, target): sources by code point, null last, with repeating weights.

    Targets share ``share`` of all words by weight up to ``passes`` times a source; what is cut off is reshared.
    In ascending order of limit over weight the sources at their limit come first, so the level is a running sum."""
    one = W.partitionBy(F.lit(0))
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("rows"))
    s = s.withColumn("sid", F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())))
    s = s.withColumn("w", F.element_at(F.array(*(F.lit(float(x)) for x in weights)), ((F.col("sid") - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("limit", F.col("source_size") * float(passes)).withColumn("ratio", F.col("limit") / F.col("w"))
    run = W.orderBy("ratio", "sid")
    before = F.coalesce(F.sum("limit").over(run.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    s = s.withColumn("level", (F.sum("source_size").over(one) * share - before) / F.sum("w").over(run.rowsBetween(0, W.unboundedFollowing)))
    s = s.withColumn("level", F.max(F.when(F.col("ratio") >= F.col("level"), F.col("level"))).over(one))
    return s.select("sid", "source", "source_size", "rows", F.least("limit", F.coalesce(F.col("level") * F.col("w"), F.col("limit"))).alias("target"))


def permuted(x: Column, n: Column, key: list[Column], rounds: int = 20) -> Column:
    """Keyed permutation of 0..n-1: each round swaps x with k - x mod n, or not, as a hash of the pair's larger number says."""

    def swap(v: Column, r: Column) -> Column:
        other = F.pmod(F.pmod(F.xxhash64(*key, r), n) - v, n)
        return F.when(F.xxhash64(F.greatest(v, other), r, *key).bitwiseAND(F.lit(1)) == 1, other).otherwise(v)

    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), x, swap)


def draw_slots(plan: DataFrame, shard_slots: int, seed: int) -> DataFrame:
    """(shard, sid, i): every slot number 0..slots-1 of every source in plan (sid, slots), dealt to shards."""
    ends = F.sum("slots").over(W.orderBy("sid").rowsBetween(W.unboundedPreceding, 0))
    spans = materialize(plan.where("slots > 0").select("sid", "slots", ends.alias("hi")).withColumn("lo", F.col("hi") - F.col("slots")))
    total = spans.agg(F.max("hi")).first()[0] or 0
    spark = plan.sparkSession
    shards = spark.range(0, -(-total // shard_slots)).select(F.col("id").alias("shard"), F.least(F.lit(shard_slots), F.lit(total) - F.col("id") * shard_slots).alias("room"))
    # a uniform draw meets the source spans that cross its grid cell, then the one that holds it
    grid = lambda c: F.floor(c * GRID / F.lit(float(max(total, 1)))).cast("int")
    cells = spans.select("sid", "lo", "hi", F.explode(F.sequence(grid(F.col("lo")), grid(F.col("hi")))).alias("g"))
    u = F.pmod(F.xxhash64("shard", "j", F.lit(seed)), F.lit(max(total, 1)))
    drawn = shards.select("shard", F.explode(F.sequence(F.lit(0), F.col("room") - 1)).alias("j")).select("shard", u.alias("u")).withColumn("g", grid(F.col("u")))
    counts = materialize(drawn.join(cells, "g").where("u >= lo and u < hi").groupBy("shard", "sid").agg(F.count(F.lit(1)).alias("c")))
    run = running_total(counts, ["sid"], "shard", "c", "upto").withColumn("past", F.col("upto") - F.col("c"))
    kept = materialize(run.join(spans.select("sid", "slots"), "sid").select("shard", "sid", F.greatest(F.lit(0), F.least("c", F.col("slots") - F.col("past"))).alias("c")))
    lack = spans.join(kept.groupBy("sid").agg(F.sum("c").alias("got")), "sid", "left").select("sid", (F.col("slots") - F.coalesce("got", F.lit(0))).alias("n")).where("n > 0")
    room = shards.join(kept.groupBy("shard").agg(F.sum("c").alias("got")), "shard", "left").select("shard", (F.col("room") - F.coalesce("got", F.lit(0))).alias("n")).where("n > 0")
    units = lambda d, k: running_total(d, [], k, "n", "end").select(k, F.explode(F.sequence(F.col("end") - F.col("n"), F.col("end") - 1)).alias("at"))
    dealt = kept.union(units(room, "shard").join(units(lack, "sid"), "at").select("shard", "sid", F.lit(1).cast("long").alias("c"))).groupBy("shard", "sid").agg(F.sum("c").alias("c")).where("c > 0")
    dealt = running_total(dealt, ["sid"], "shard", "c", "end")
    # slots are numbered where their shard's share of a source is, whatever the source's size
    tasks = max(1, min(MAX_TASKS, -(-total // TASK_SLOTS)))
    return dealt.repartition(tasks, "sid", "shard").select("shard", "sid", F.explode(F.sequence(F.col("end") - F.col("c"), F.col("end") - 1)).alias("i"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", block: int = 64, shard_slots: int = 4096, share: float = 1.5, passes: int = 2, weights: tuple[float, ...] = WEIGHTS, seed: int = 20) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(documents, blocks, slots).

    documents: id, key (hash of the text), size, source, source_size, target, taken for every row; blocks: sid, b,
    rid, at, words (which words of which document fill a block); slots: shard, sid, i, b. Null texts have no words
    and are never taken, null sources are one source, repeated rows are laid out each; results don't depend on how
    the input is split. The source table is the only thing that may be broadcast, if Spark finds it small."""
    c = F.col(text_col)
    rows = materialize(docs.select(F.col(id_col).alias("id"), F.xxhash64(c).alias("key"), F.col(source_col).alias("source"), F.coalesce(F.regexp_count(c, F.lit(WORD)), F.lit(0)).cast("long").alias("size")).withColumn("rid", F.monotonically_increasing_id()))
    srcs = materialize(source_targets(rows, weights, share, passes))
    plan = srcs.withColumn("blocks", F.ceil(F.col("source_size") / block)).withColumn("slots", F.when(F.col("source_size") > 0, F.least(F.col("blocks") * passes, F.round(F.col("target") * F.col("blocks") / F.col("source_size")).cast("long"))).otherwise(F.lit(0)))
    plan = materialize(plan)

    cells = -(-rows.count() // CELL_ROWS) or 1
    laid = rows.join(plan, rows["source"].eqNullSafe(plan["source"])).select("rid", "id", "key", rows["source"], "size", "sid", "source_size", "target")
    laid = laid.withColumn("h", F.xxhash64("id", "key", F.lit(seed))).withColumn("cell", F.pmod("h", F.lit(cells)))
    starts = running_total(laid.groupBy("sid", "cell").agg(F.sum("size").alias("n")), ["sid"], "cell", "n", "upto").select("sid", "cell", (F.col("upto") - F.col("n")).alias("from"))
    inner = F.sum("size").over(W.partitionBy("sid", "cell").orderBy("h", "id", "key", "rid").rowsBetween(W.unboundedPreceding, 0))
    laid = materialize(laid.withColumn("inner", inner).join(starts, ["sid", "cell"]).withColumn("at", F.col("from") + F.col("inner") - F.col("size")).drop("h", "cell", "from", "inner"))

    lo, hi = F.greatest("at", F.col("b") * block), F.least(F.col("at") + F.col("size"), (F.col("b") + 1) * block)
    blocks = laid.where("size > 0").select("rid", "sid", "at", "size", F.explode(F.sequence(F.floor(F.col("at") / block), F.floor((F.col("at") + F.col("size") - 1) / block))).alias("b")).select("sid", "b", "rid", (lo - F.col("at")).alias("at"), (hi - lo).alias("words"))
    numbered = draw_slots(plan, shard_slots, seed).join(plan.select("sid", "blocks"), "sid")
    e = F.floor(F.col("i") / F.col("blocks"))
    slots = numbered.select("shard", "sid", "i", permuted(F.pmod("i", F.col("blocks")), F.col("blocks"), [F.col("sid"), e, F.lit(seed)]).alias("b"))
    used = slots.groupBy("sid", "b").agg(F.count(F.lit(1)).alias("times"))
    taken = blocks.join(used, ["sid", "b"]).groupBy("rid").agg(F.sum(F.col("words") * F.col("times")).alias("taken"))
    out = laid.join(taken, "rid", "left").select("id", "key", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0).cast("long")).alias("taken"))
    return out, blocks, slots


def op6_multinomial_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mix(table(spark, sf_dir, "documents"))[0]
    return out.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with what the mix takes of them: size, source_size, target and taken, with an underscore where the
    input has a column of that name. Rows of equal id and text carry the mean of their takes."""
    told = ["size", "source_size", "target", "taken"]
    out = mix(docs)[0].groupBy("id", "key", *told[:3]).agg(F.floor(F.avg("taken")).alias("taken"))
    key, i, k, *new = unused(docs.columns, "key", "id", "k", *told)
    out = out.select(F.col("id").alias(i), F.col("key").alias(k), *(F.col(a).alias(b) for a, b in zip(told, new, strict=True)))
    d = docs.withColumn(key, F.xxhash64("text"))
    return d.join(out, F.col("doc_id").eqNullSafe(F.col(i)) & F.col(key).eqNullSafe(F.col(k))).select(*docs.columns, *new)
