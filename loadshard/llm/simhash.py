"""SimHash near-duplicates linked through Golay-code keys.

A 64-bit fingerprint is cut into segments of 23, 23 and 18 bits. The perfect (23, 12) Golay code decodes a
segment, and each of its one-bit neighbours, to codeword indices; two segments that differ in at most two
bits have a decoded midpoint in common, so they share an index. Two errors over three segments leave one
segment whole, hence the keys: one whole segment beside the indices of another. Candidates of a key are
verified by their Hamming distance. Keys with more than ``bucket_cap`` fingerprints go another exact way:
fingerprints within two bits have a common one-bit neighbour, and a neighbour has at most 65 of them.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.llm.common import classes_in_parts, connected_components, lower_ascii, materialize, table, texts_of, unused, words_of
from loadshard.llm.linededup import BANDS, minhash_bands

#: Fixed value: generator polynomial of the binary Golay code.
GOLAY_POLYNOMIAL = 0xC75
SEGMENTS = ((0, 23), (23, 23), (46, 18))
#: (whole segment, decoded segment)
KEYS = ((0, 1), (1, 0), (2, 0))


@lru_cache(1)
def golay_table() -> np.ndarray:
    """Codeword index of each of the 2^23 words: spheres of radius three around codewords fill the space."""
    index = np.arange(4096, dtype=np.int32)
    rest = index << 11
    for bit in range(22, 10, -1):
        rest ^= np.where(rest >> bit & 1, GOLAY_POLYNOMIAL << (bit - 11), 0)
    errors = [sum(1 << b for b in bits) for n in range(4) for bits in combinations(range(23), n)]
    out = np.empty(1 << 23, np.int16)
    out[((index << 11) | rest)[:, None] ^ np.array(errors, np.int32)[None, :]] = index[:, None]
    return out


def golay_keys(fingerprints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) pairs of int64 fingerprints; keys of a row are distinct."""
    decode, fp = golay_table(), fingerprints.astype(np.int64).view(np.uint64)
    rows, keys = [], []
    for kind, (whole, near) in enumerate(KEYS):
        part = [((fp >> np.uint64(at)) & np.uint64((1 << width) - 1)).astype(np.int64) for at, width in (SEGMENTS[whole], SEGMENTS[near])]
        around = np.stack([decode[part[1]], *(decode[part[1] ^ (1 << b)] for b in range(23))], 1).astype(np.int64)
        around.sort(axis=1)
        new = np.ones(around.shape, bool)
        new[:, 1:] = around[:, 1:] != around[:, :-1]
        r, c = np.nonzero(new)
        rows.append(r)
        keys.append((kind << 40) | (part[0][r] << 12) | around[r, c])
    return np.concatenate(rows), np.concatenate(keys)


def _keyed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        for at in range(0, len(b), 4_000):
            part = b.iloc[at : at + 4_000]
            fp, t = part["fp"].to_numpy(), part["t"].to_numpy()
            rows, keys = golay_keys(fp)
            yield pd.DataFrame({"t": t[rows], "fp": fp[rows], "key": keys})


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """(rid, id, fp): 64-bit SimHash of each whole text; no words (also null): zero. rid tells repeated ids apart."""
    base = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("id"), words_of(lower_ascii(F.col(text_col))).alias("w"))
    n = F.size("w")
    shifted = [F.slice("w", k + 1, F.greatest(n - shingle + 1, F.lit(0))) for k in range(shingle)]
    pieces = F.when(n >= shingle, F.arrays_zip(*(s.alias(f"w{k}") for k, s in enumerate(shifted))))
    names = [f"w{k}" for k in range(shingle)]
    short = F.array(F.struct(F.array_join("w", " ").alias(names[0]), *(F.lit(None).cast("string").alias(x) for x in names[1:])))
    cast = "array<struct<" + ",".join(f"{x}:string" for x in names) + ">>"
    rows = base.select("rid", "id", F.explode_outer(F.when(n >= shingle, pieces.cast(cast)).when(n > 0, short.cast(cast))).alias("s"))
    text = F.concat_ws(" ", *(F.col(f"s.{x}") for x in names))
    hashed = rows.select("rid", "id", F.when(F.col("s").isNotNull(), F.xxhash64(text)).alias("h"))
    sums = hashed.groupBy("rid", "id").agg(F.count("h").alias("n"), *_counters("h", "c"))
    return sums.select("rid", "id", _majority("c").alias("fp"))


def _counters(h: str, name: str) -> list[Column]:
    """How many hashes have a bit set; the counts of bits i and i + 32 ride in one sum."""
    both = F.lit(0x0000000100000001).cast("long")
    return [F.sum(F.shiftrightunsigned(h, i).bitwiseAND(both)).alias(f"{name}{i}") for i in range(32)]


def _majority(name: str) -> Column:
    """64 bits, each set where over half of n hashes have it; zero without hashes."""

    def bit(i: int) -> Column:
        c = F.col(f"{name}{i % 32}")
        count = F.shiftrightunsigned(c, 32) if i > 31 else c.bitwiseAND(F.lit(0xFFFFFFFF))
        return F.when(2 * count > F.col("n"), F.shiftleft(F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))

    fp = bit(0)
    for i in range(1, 64):
        fp = fp.bitwiseOR(bit(i))
    return F.coalesce(fp, F.lit(0).cast("long"))


def _majority_of(counts: str) -> Column:
    """The same from an array of the 32 double counters; a small expression where many tables are made."""

    def with_bit(acc: Column, i: Column) -> Column:
        c = F.get(F.col(counts), i % 32)
        count = F.when(i > 31, F.shiftrightunsigned(c, 32)).otherwise(c.bitwiseAND(F.lit(0xFFFFFFFF)))
        return F.when(2 * count > F.col("n"), acc.bitwiseOR(F.get(F.lit([1 << b if b < 63 else -(1 << 63) for b in range(64)]), i))).otherwise(acc)

    return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), with_bit)


def distance(a: str | Column, b: str | Column) -> Column:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.bit_count(a.bitwiseXOR(b))


def links(fps: DataFrame, bucket_cap: int = 64) -> DataFrame:
    """(t, a, b) links that join exactly the distinct fingerprints (columns t, fp) of a table t within two bits of each
    other into components."""
    keyed = materialize(fps.select("t", "fp").distinct().mapInPandas(_keyed, "t int, fp long, key long"))
    sized = keyed.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = keyed.join(sized, ["t", "key"])
    lists = shared.where(F.col("n") <= bucket_cap).groupBy("t", "key").agg(F.collect_list("fp").alias("l")).select("t", "l", F.explode("l").alias("a"))
    pairs = lists.select("t", "a", F.explode("l").alias("b")).where((F.col("a") < F.col("b")) & (distance("a", "b") <= 2))
    crowded = shared.where(F.col("n") > bucket_cap).select("t", "fp").distinct()
    flips = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(F.shiftleft(F.lit(1).cast("long"), i)) for i in range(64)))
    stars = crowded.select("t", "fp", F.explode(flips).alias("mid")).groupBy("t", "mid").agg(F.collect_list("fp").alias("l")).where(F.size("l") > 1)
    return pairs.union(stars.select("t", F.array_min("l").alias("a"), F.explode("l").alias("b")).where("a <> b")).distinct()


def components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, bucket_cap: int = 64) -> DataFrame:
    """(id, fp, component_id) per row: the smallest id reachable through fingerprints at most two bits apart.

    Null and blank texts have fingerprint zero and link like others; repeated rows share a class; null ids
    keep a row and never name a component unless all ids of it are null; an empty table gives no rows."""
    fps = materialize(fingerprints(docs, id_col, text_col, shingle))
    classes = fps.groupBy("fp").agg(F.min("id").alias("rep"))
    linked = connected_components(links(fps.withColumn("t", F.lit(0)), bucket_cap)).select(F.col("node").alias("fp"), "component")
    rooted = materialize(classes.join(linked, "fp", "left").withColumn("root", F.coalesce("component", "fp")).select("fp", "rep", "root"))
    least = rooted.groupBy("root").agg(F.min("rep").alias("component_id"))
    named = materialize(rooted.join(least, "root").select("fp", "component_id"))
    return fps.join(named, "fp").select("id", "rid", "fp", "component_id")


SEEDS = (42, 7, 19, 101, 3, 57, 211, 1009)
PART_WORDS = 200_000


def shingles(text: str, size: int) -> frozenset[str]:
    w = text.lower().split()
    return frozenset(" ".join(w[i : i + size]) for i in range(max(1, len(w) - size + 1)))


def shingle_bands(texts: list[list[int]], size: int) -> np.ndarray:
    """texts x BANDS keys of the shingles of texts, each given as the hashes of its words, at least one."""
    padded = [w if len(w) >= size else w + [0] * (size - len(w)) for w in texts]
    n = np.array([len(w) for w in padded])
    w = np.fromiter((x for p in padded for x in p), np.uint64, n.sum())
    h = np.zeros(len(w) - size + 1, np.uint64)
    for k in range(size):
        h = (h ^ w[k : k + len(h)]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    inside = np.ones(len(h), bool)  # windows that cross a text's end are left out
    for k in range(1, size):
        inside[np.cumsum(n)[:-1] - k] = False
    n = n - size + 1
    return minhash_bands(h[inside], np.cumsum(n) - n)


def banded_texts(docs: DataFrame, size: int) -> DataFrame:
    """(h, band): MinHash bands of the shingles of texts (h, text) with words; a task tells a run of equal texts once."""

    def rows(held: dict[int, list[int]]) -> pa.RecordBatch:
        keys = shingle_bands(list(held.values()), size).view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(np.fromiter(held, np.int64, len(held)), BANDS)), pa.array(keys.ravel())], names=["h", "band"])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        held: dict[int, list[int]] = {}
        total = 0
        for b in batches:
            for h, t in zip(b.column("h").to_pylist(), texts_of(b.column("text")), strict=True):
                if h in held or not (w := t.lower().split()):
                    continue
                for x in set(w).difference(known):
                    known[x] = xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass"))
                held[h] = [known[x] for x in w]
                total += len(w)
                if total > 200_000:
                    yield rows(held)
                    held, total = {}, 0
                if len(known) > 500_000:
                    known = {}
        if held:
            yield rows(held)

    return docs.select("h", "text").mapInArrow(read, "h long, band long")


def text_classes(docs: DataFrame, text_col: str = "text", threshold: float = 0.8, shingle: int = 5) -> DataFrame:
    """(h, root): hashes of distinct texts that have a near copy, and the smallest hash of their class.

    Texts whose distinct words have a fingerprint within two bits under any of SEEDS, or that share a MinHash band of
    their shingles (probability 0.998 at a similarity of 0.8), are candidates; the texts of a candidate component are gathered once and compared by exact Jaccard similarity of word shingles. Components over PART_WORDS
    are compared in parts, then every two parts with each other."""
    base = docs.select(F.coalesce(text_col, F.lit("")).alias("text")).withColumn("h", F.xxhash64("text"))
    # copies of a text multiply all of its counts alike, so a hash stands for its rows
    words = base.select("h", F.explode(F.array_distinct(words_of(lower_ascii(F.col("text"))))).alias("w"))
    rows = words.select("h", F.posexplode(F.array(*(F.xxhash64("w", F.lit(s)) for s in SEEDS))).alias("t", "x"))
    sums = rows.groupBy("h", "t").agg(F.count(F.lit(1)).alias("n"), *_counters("x", "c"))
    fps = materialize(sums.select("h", "n", "t", F.array(*(F.col(f"c{i}") for i in range(32))).alias("counts")).select("h", "n", "t", _majority_of("counts").alias("fp")))
    first = fps.groupBy("t", "fp").agg(F.min("h").alias("rep"), F.max("h").alias("most"))
    same = fps.join(first.where("rep < most"), ["t", "fp"]).where("h <> rep").select(F.col("h").alias("a"), F.col("rep").alias("b"))
    near = links(fps)
    ends = near.join(first.select("t", F.col("fp").alias("a"), F.col("rep").alias("ra")), ["t", "a"]).join(first.select("t", F.col("fp").alias("b"), F.col("rep").alias("rb")), ["t", "b"])
    low = F.min("h").over(W.partitionBy("band"))
    banded = banded_texts(base, shingle).withColumn("b", low).where("h <> b").select(F.col("h").alias("a"), "b")
    found = connected_components(same.union(ends.select("ra", "rb")).union(banded).distinct()).select(F.col("node").alias("h"), F.col("component").alias("group"))
    sized = found.join(fps.where("t = 0").select("h", "n"), "h")
    total = sized.groupBy("group").agg(F.sum("n").alias("total"))
    dealt = sized.join(total, "group").select("h", "group", F.when(F.col("total") > PART_WORDS, F.pmod(F.xxhash64("h", "group"), F.ceil(2 * F.col("total") / PART_WORDS))).otherwise(0).alias("part"))
    held = materialize(base.join(dealt, "h").groupBy("h", "group", "part").agg(F.first("text").alias("text")))
    return classes_in_parts(held, "text", lambda t: shingles(t, shingle), threshold)


def near_deduped(spark: SparkSession, docs: DataFrame, sf_dir: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each class of equal or near-equal texts stays: the one with the smallest id (null ids first).

    Null and empty texts are one class; of rows that repeat an id and text one stays."""
    key = F.xxhash64(F.coalesce(text_col, F.lit("")))
    rows = docs.select(F.col(id_col).alias("id"), key.alias("h"))
    classes = materialize(text_classes(docs, text_col))
    placed = materialize(rows.join(classes, "h", "left").select("id", "h", F.coalesce("root", "h").alias("root")).groupBy("root", "h", "id").agg(F.count(F.lit(1)).alias("n")))
    kept = placed.groupBy("root").agg(F.min(F.struct("id", "h")).alias("k"))
    mine, i, k = unused(docs.columns, "key", "id", "k")
    late = placed.join(kept, "root").where(~F.struct("id", "h").eqNullSafe(F.col("k")))
    gone = late.select(F.col("id").alias(i), F.col("h").alias(k))
    d = docs.withColumn(mine, key)
    out = d.join(gone, F.col(id_col).eqNullSafe(F.col(i)) & (F.col(mine) == F.col(k)), "left_anti")
    if not placed.where("n > 1").isEmpty():
        out = out.dropDuplicates([id_col, mine])
    return out.select(*docs.columns)


def op5_simhash_golay(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = components(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
