from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from loadshard.operators import layout
from loadshard.operators.allocation import place
from loadshard.operators.fragments import fragment
from loadshard.operators.store import bootstrap, from_sites, open_store, save_catalogue, site_summaries
from loadshard.sources.mapping import triples
from loadshard.sources.ntriples import read_csv, read_ntriples, write_csv, write_ntriples
from loadshard.streaming import updates
from loadshard.workload.catalogue import text_of
from loadshard.workload.load import analyse, load_queries
from tests.conftest import rows_of

TABLES = ("region", "nation", "customer", "orders")


@pytest.fixture
def store(spark, sf, tmp_path):
    t = triples(spark, sf, TABLES)
    fr = fragment(analyse(load_queries(spark, [(q, text_of(q), 1) for q in ("b05", "b07", "b08", "b16")]), 1), t)
    return bootstrap(spark, t, fr, place(fr, 3), str(tmp_path / "store"))


def ops(spark, rows):
    return spark.createDataFrame([(i, op, None, s, p, o, k, None) for i, op, s, p, o, k in rows], updates.OPS)


def test_batch_is_a_rebuild(spark, sf, store):
    events = spark.read.parquet(f"{sf}/events.parquet")
    want = updates.settle(triples(spark, sf, TABLES), updates.from_events(events))
    got = updates.apply_batch(store, updates.from_events(events), 1)
    assert rows_of(got.triples.select("s", "p", "o", "o_kind")) == rows_of(want.select("s", "p", "o", "o_kind"))
    again = updates.apply_batch(got, updates.from_events(events), 1)
    assert again.triples.count() == want.count()
    # every triple lies where its definition says
    placed = store.fragmentation.assign(got.triples.drop("frag_id", "site_id")).select("s", "p", "o", "frag_id")
    assert rows_of(placed) == rows_of(got.triples.select("s", "p", "o", "frag_id"))


def test_modifications(spark, store):
    order = store.triples.where("p = 'p:o_orderstatus' and o = 'P'").select("s").first()
    order = order[0] if order else store.triples.where("p = 'p:o_orderstatus' and o <> 'F'").select("s").first()[0]
    batch = ops(spark, [(1, "modify", order, "p:o_orderstatus", "F", "str"), (2, "modify", "customer:1", "p:c_name", "new", "str"), (2, "modify", "customer:1", "p:c_name", "new", "str"), (3, "delete", "nobody", "p:x", "y", "str"), (4, "insert", "new:1", "p:unseen", "z", "str")])
    split = {r["s"]: r for r in updates.split_modifications(batch, store).collect()}
    assert split[order]["old_frag"] != split[order]["frag_id"]
    assert split["customer:1"]["local"]
    after = updates.apply_batch(store, batch, 5).triples
    assert [r["o"] for r in after.where((F.col("s") == order) & (F.col("p") == "p:o_orderstatus")).collect()] == ["F"]
    assert [r["o"] for r in after.where("s = 'customer:1' and p = 'p:c_name'").collect()] == ["new"]
    fresh = after.where("s = 'new:1'").collect()
    assert len(fresh) == 1 and fresh[0]["frag_id"] == store.fragmentation.remainder.number


def test_stream_equals_batch(spark, sf, store, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(1).write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    q, held = updates.stream(source, store, str(tmp_path / "ck"))
    q.awaitTermination(120)
    want = updates.settle(triples(spark, sf, TABLES), updates.from_events(events))
    assert rows_of(held["store"].triples.select("s", "p", "o")) == rows_of(want.select("s", "p", "o"))


def test_relocation_keeps_all_triples(spark, store):
    n = store.triples.count()
    before = store.placement.imbalance
    after = updates.relocate(store, 1.1)
    assert after.triples.count() == n
    assert max(s.load for s in after.placement.sites) / after.placement.uniform <= before


def test_text_formats(spark, sf, tmp_path):
    t = triples(spark, sf, ("nation", "orders")).union(spark.createDataFrame([("a", "p:t", 'x "y"\n\\n', "str", None)], "s string, p string, o string, o_kind string, o_num double"))
    write_ntriples(t, str(tmp_path / "nt"))
    assert rows_of(read_ntriples(spark, str(tmp_path / "nt"))) == rows_of(t)
    plain = t.where("p <> 'p:t'")
    write_csv(plain, str(tmp_path / "csv"))
    assert rows_of(read_csv(spark, str(tmp_path / "csv"))) == rows_of(plain)


def bucketed(spark, sf, path, buckets=4):
    t = triples(spark, sf, TABLES)
    fr = fragment(analyse(load_queries(spark, [(q, text_of(q), 1) for q in ("b05", "b07", "b08", "b16")]), 1), t)
    return bootstrap(spark, t, fr, place(fr, 3), path, buckets=buckets)


@pytest.mark.parametrize("buckets", [0, 4])
def test_a_failed_batch_leaves_the_store_whole(spark, sf, tmp_path, monkeypatch, buckets):
    store = bucketed(spark, sf, f"file://{tmp_path}/s", buckets)
    before = rows_of(store.triples)
    batch = ops(spark, [(1, "modify", "customer:1", "p:c_name", "new", "str"), (2, "insert", "new:1", "p:unseen", "z", "str"), (3, "delete_subject", "nation:3", None, None, None)])
    commit = layout.commit

    def broken(*_):
        raise OSError("lost")

    for name in ("commit", "write"):  # after all data are written, and before any are
        monkeypatch.setattr(layout, name, broken)
        with pytest.raises(OSError):
            updates.apply_batch(store, batch, 1)
        monkeypatch.undo()
        assert layout.commit is commit and rows_of(updates.current(store).triples) == before
    after = updates.apply_batch(store, batch, 1)
    assert rows_of(store.triples) == before  # an open snapshot stays readable
    want = updates.settle(store.triples.select("s", "p", "o", "o_kind", "o_num"), batch)
    assert rows_of(after.triples.select("s", "p", "o", "o_kind", "o_num")) == rows_of(want)
    assert after.snapshot.batches == (1,) and updates.apply_batch(store, batch, 1).snapshot == after.snapshot


def test_batches_keep_statistics_and_the_catalogue(spark, sf, tmp_path):
    path = str(tmp_path / "s")
    store = bucketed(spark, sf, path)
    for i in range(4):
        former = store.snapshot
        store = updates.apply_batch(store, ops(spark, [(1, "modify", f"customer:{i + 1}", "p:c_name", f"new{i}", "str"), (2, "insert", f"new:{i}", "p:unseen", "9", "num")]), i)
    recount = from_sites(site_summaries(store.triples))
    assert store.stats.total == recount.total and set(store.stats.properties) == set(recount.properties)
    for p, a in store.stats.properties.items():
        b = recount.properties[p]
        assert (a.rows, a.low, a.high) == (b.rows, b.low, b.high)
        assert abs(a.subjects - b.subjects) <= 0.03 * b.subjects + 1 and abs(a.objects - b.objects) <= 0.03 * b.objects + 1  # sketches
    sizes = {r["frag_id"]: r["count"] for r in store.triples.groupBy("frag_id").count().collect()}
    assert {f.number: f.size for f in store.fragmentation.fragments if f.size} == sizes
    # only the partitions of this snapshot and of the one before are on disk
    held = layout.newest(spark, path)
    on_disk = {x for v in range(held.version + 1) for x in layout.parts_of_version(spark, path, v)}
    assert on_disk == held.live | former.live
    assert held.batches == (0, 1, 2, 3)
    save_catalogue(store, str(tmp_path / "c.json"))
    spark.sql(f"DROP TABLE {layout.table_name(path)}")  # as in another session
    again = open_store(spark, str(tmp_path / "c.json"), store.fragmentation.analysis)
    assert rows_of(again.triples) == rows_of(store.triples) and again.snapshot == store.snapshot
    more = updates.apply_batch(again, ops(spark, [(1, "insert", "new:1", "p:unseen", "10", "num")]), 9)
    assert more.triples.count() == store.triples.count() + 1
    moved = updates.relocate(more, 1.05)
    assert rows_of(moved.triples.drop("site_id")) == rows_of(more.triples.drop("site_id"))
