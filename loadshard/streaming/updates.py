"""Updates of a placed store: routing by fragment definitions, batches, and a stream of events.

Files are immutable, so a batch writes the (site, fragment) partitions it touches anew, as a further version, and no others.
One manifest then names the new partitions, the kept ones and the batch's number: a batch that fails before it leaves the
store as it was, and a number already there is not applied again."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from loadshard.functions.shared import materialize
from loadshard.operators import layout
from loadshard.operators.allocation import rebalance, site_column
from loadshard.operators.store import Store, dealt, from_sites, live_summaries, write_summaries
from loadshard.sources.mapping import BY_NAME, table_triples

#: op_id, op (insert, delete, delete_subject, modify), ts, s, p, o, o_kind, o_num; for modify o is the new object.
OPS = "op_id long, op string, ts timestamp_ntz, s string, p string, o string, o_kind string, o_num double"


def from_events(events: DataFrame) -> DataFrame:
    """Operations that events stand for: all but errors insert the event; a purchase sets the user's last purchase, a
    signup the user's segment; an error deletes the event before it."""
    m = BY_NAME["events"]
    live = events.where("event_type <> 'error'")
    body = table_triples(live.select("event_id", "ts", "user_id", "event_type", "value", "props"), m)
    at = events.select(F.concat(F.lit("event:"), F.col("event_id").cast("string")).alias("s"), "event_id", F.col("ts").alias("at"))
    ins = body.join(at, "s").select((F.col("event_id") * 4).alias("op_id"), F.lit("insert").alias("op"), F.col("at").alias("ts"), "s", "p", "o", "o_kind", "o_num")
    who = F.concat(F.lit("customer:"), F.col("user_id").cast("string"))
    money = F.col("value").cast("decimal(18,2)")
    none = F.lit(None).cast("double")
    buy = events.where("event_type = 'purchase'").select((F.col("event_id") * 4 + 1).alias("op_id"), F.lit("modify").alias("op"), "ts", who.alias("s"), F.lit("p:last_purchase").alias("p"), money.cast("string").alias("o"), F.lit("num").alias("o_kind"), money.cast("double").alias("o_num"))
    sign = events.where("event_type = 'signup'").select((F.col("event_id") * 4 + 2).alias("op_id"), F.lit("modify").alias("op"), "ts", who.alias("s"), F.lit("p:c_mktsegment").alias("p"), F.lit("BUILDING").alias("o"), F.lit("str").alias("o_kind"), none.alias("o_num"))
    gone = events.where("event_type = 'error'").select((F.col("event_id") * 4 + 3).alias("op_id"), F.lit("delete_subject").alias("op"), "ts", F.concat(F.lit("event:"), (F.col("event_id") - 1).cast("string")).alias("s"), *(F.lit(None).cast("string").alias(c) for c in ("p", "o", "o_kind")), none.alias("o_num"))
    return ins.union(buy).union(sign).union(gone)


def route(ops: DataFrame, store: Store) -> DataFrame:
    """ops with frag_id and site_id: the same codes that place triples, no shuffle. Whole-subject deletes have none;
    they go to every fragment that may hold the subject."""
    coded = store.fragmentation.assign(ops.withColumn("p", F.coalesce("p", F.lit("")))).withColumn("site_id", site_column(store.placement))
    whole = F.col("op") == "delete_subject"
    return coded.withColumns({"p": F.when(whole, None).otherwise(F.col("p")), "frag_id": F.when(whole, None).otherwise(F.col("frag_id")), "site_id": F.when(whole, None).otherwise(F.col("site_id"))})


def split_modifications(ops: DataFrame, store: Store) -> DataFrame:
    """Modifications of (s, p) with their old place: op_id, s, p, old_frag, old_site, frag_id, site_id, local. A local
    one stays on its site; others are a delete at the old site and an insert at the new one."""
    new = route(ops.where("op = 'modify'"), store)
    old = store.triples.select("s", "p", F.col("frag_id").alias("old_frag"), F.col("site_id").alias("old_site"))
    return new.join(old, ["s", "p"], "left").withColumn("local", F.coalesce(F.col("old_site") == F.col("site_id"), F.lit(False))).select("op_id", "s", "p", "old_frag", "old_site", "frag_id", "site_id", "local")


def settle(triples: DataFrame, ops: DataFrame) -> DataFrame:
    """The triples after a batch in op_id order: for each triple the last operation on it decides, be it its own insert
    or delete, a later modification of its (s, p), or a later delete of its subject. Repeated op_ids count once."""
    ops = ops.dropDuplicates(["op_id", "s", "p", "o", "o_kind"])
    made = ops.where("op in ('insert', 'modify')").groupBy("s", "p", "o", "o_kind").agg(F.max("op_id").alias("made"), F.max("o_num").alias("o_num"))
    base = triples.select("s", "p", "o", "o_kind", "o_num").withColumn("made", F.lit(-1).cast("long"))
    every = base.unionByName(made).groupBy("s", "p", "o", "o_kind").agg(F.max("made").alias("made"), F.max("o_num").alias("o_num"))
    cut = ops.where("op = 'delete'").groupBy("s", "p", "o", "o_kind").agg(F.max("op_id").alias("cut"))
    swap = ops.where("op = 'modify'").groupBy("s", "p").agg(F.max("op_id").alias("swap"))
    gone = ops.where("op = 'delete_subject'").groupBy("s").agg(F.max("op_id").alias("gone"))
    last = every.join(cut, ["s", "p", "o", "o_kind"], "left").join(swap, ["s", "p"], "left").join(gone, "s", "left")
    return last.where("made > coalesce(cut, -2) and made >= coalesce(swap, -2) and made > coalesce(gone, -2)").select("s", "p", "o", "o_kind", "o_num")


def apply(triples: DataFrame, ops: DataFrame, store: Store) -> DataFrame:
    """Placed triples after a batch; triples whose subject the batch doesn't name are passed through unread by joins."""
    named = ops.select("s").distinct()
    touched = triples.join(named, "s", "left_semi")
    rest = triples.join(named, "s", "left_anti")
    new = store.fragmentation.assign(settle(touched, ops)).withColumn("site_id", site_column(store.placement))
    return rest.select("s", "p", "o", "o_kind", "o_num", "site_id", "frag_id").unionByName(new.select("s", "p", "o", "o_kind", "o_num", "site_id", "frag_id"))


def apply_batch(store: Store, ops: DataFrame, batch_id: int) -> Store:
    """Writes anew the partitions that hold or get triples of the batch's subjects, then switches to them."""
    spark = ops.sparkSession
    store = current(store)
    if batch_id in store.snapshot.batches:
        return store
    ops = materialize(ops)
    named = ops.select("s").distinct()
    old_parts = store.triples.join(named, "s", "left_semi").select("site_id", "frag_id")
    new_parts = route(ops, store).where("frag_id is not null").select("site_id", "frag_id")
    parts = {(r[0], r[1]) for r in old_parts.union(new_parts).distinct().collect()}  # at most sites x fragments
    after = apply(_held(store, parts), ops, store) if parts else None
    return switch(store, after, parts, batch_id)


def _held(store: Store, parts: set[tuple[int, int]]) -> DataFrame:
    """The triples of some partitions, by a filter on partition columns."""
    sites, frags = (sorted({x[i] for x in parts}) for i in (0, 1))
    named = F.concat_ws("/", "site_id", "frag_id").isin([f"{a}/{b}" for a, b in sorted(parts)])
    return store.triples.where(F.col("site_id").isin(sites) & F.col("frag_id").isin(frags) & named)


def switch(store: Store, rows: DataFrame | None, parts: set[tuple[int, int]], batch_id: int | None = None) -> Store:
    """The store with the partitions ``parts`` replaced by ``rows``: all data first, then the manifest."""
    spark, now = store.triples.sparkSession, store.snapshot
    version = now.version + 1
    made = frozenset()
    if rows is not None:
        layout.write(dealt(rows, store.fragmentation, store.placement, buckets=store.buckets), store.path, version, store.buckets)
        made = layout.parts_of_version(spark, store.path, version)
        if made:
            write_summaries(spark.read.schema(layout.SCHEMA).parquet(store.path), store.path, version)
    kept = frozenset(x for x in now.live if (x[1], x[2]) not in parts)
    layout.commit(spark, store.path, layout.Snapshot(version, kept | made, (*now.batches, *([] if batch_id is None else [batch_id]))))
    return current(store)


def current(store: Store) -> Store:
    """The store as its newest manifest has it."""
    spark = store.triples.sparkSession
    now = layout.newest(spark, store.path)
    if now == store.snapshot:
        return store
    return refresh(replace(store, triples=layout.read(spark, store.path, store.buckets, now), snapshot=now))


def refresh(store: Store) -> Store:
    """Fragment sizes and statistics from the kept summaries; no triple is read, whatever the store's size."""
    told = live_summaries(store.triples.sparkSession, store.path, store.snapshot)
    sizes = {r[0]: r[1] for r in told.groupBy("frag_id").agg(F.sum("n")).collect()}
    for f in store.fragmentation.fragments:
        f.size = sizes.get(f.number, 0)
    by = {f.number: f for f in store.fragmentation.fragments}
    for s in store.placement.sites:
        s.load = sum(by[f].load for f in s.fragments)
    return replace(store, stats=from_sites(told, store.stats.pairs))


def relocate(store: Store, tolerance: float = 1.5) -> Store:
    """Moves fragments off overloaded sites in one switch; only the moved fragments' partitions are written anew."""
    store = current(store)
    moved: dict[int, tuple[int, int]] = {}
    for f, a, b in rebalance(store.placement, store.fragmentation, tolerance):
        moved[f] = (moved.get(f, (a, b))[0], b)
    if not moved:
        return store
    left = {(a, f) for f, (a, _) in moved.items()}
    site = F.coalesce(*(F.when(F.col("frag_id") == f, F.lit(b)) for f, (_, b) in moved.items()))
    out = switch(store, _held(store, left).withColumn("site_id", site), left)
    for f, (_, b) in moved.items():
        out.placement.site_of[f] = b
        for s in out.placement.sites:
            s.fragments = [x for x in s.fragments if x != f] + ([f] if s.number == b else [])
    return refresh(out)


def stream(events: DataFrame, store: Store, checkpoint: str, lateness: str = "1 day"):
    """Starts a query that applies an event stream in micro-batches. Late events beyond the watermark and repeats of an
    event within it are dropped; a replayed batch is not applied twice."""
    held = {"store": store}

    def each(batch: DataFrame, batch_id: int) -> None:
        held["store"] = apply_batch(held["store"], from_events(batch), batch_id)

    clean = events.withColumn("wm", F.col("ts").cast("timestamp")).withWatermark("wm", lateness).dropDuplicatesWithinWatermark(["event_id"]).drop("wm")
    return clean.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(), held


def load_windows(ops: DataFrame, store: Store, window: str = "1 hour") -> DataFrame:
    """(window, frag_id, n): operations by fragment and tumbling window."""
    return route(ops, store).groupBy(F.window("ts", window).alias("window"), "frag_id").agg(F.count(F.lit(1)).alias("n"))


