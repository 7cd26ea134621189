"""Quality classifier by nearest-neighbour voting in a latent-semantic space.

Terms are trigrams over sixteen character classes and graded style marks (length, distinct words, repeated words
and lines, word length). Document frequencies come from all documents. A randomised SVD of a bounded labelled
sample gives the latent space; the sample's latent vectors, at most ``max_labelled`` of ``rank`` floats, are broadcast, and
every document meets all of them in exact blocked cosine products. The nearest vote with weights that fall with
distance.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.llm.common import table, texts_of, unused

#: Fixed value: each character class; the rest of ASCII is class 15, letters beyond ASCII are lower case.
CLASSES = ("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", " \t\r\x0b\x0c", "\n", ".", ",", "!?", "#", "$", "%", "&", "*", "|", "\"'")
TRIGRAMS = 16**3
MARKS = 6
STEPS = 8  # graded places of a mark
TERMS = TRIGRAMS + MARKS * STEPS


def _class_table() -> np.ndarray:
    t = np.full(256, 15, np.uint16)
    t[128:] = 0
    for i, chars in enumerate(CLASSES):
        for c in chars:
            t[ord(c)] = i
    return t


CLASS_OF = _class_table()


def term_counts(text: str | None) -> np.ndarray:
    """Dampened term counts of one whole text."""
    out = np.zeros(TERMS, np.float32)
    if not text:
        return out
    raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    raw = raw[(raw & 0xC0) != 0x80]  # one unit a code point
    c = CLASS_OF[raw]
    if len(c) > 2:
        out[:TRIGRAMS] = np.bincount(c[:-2] * 256 + c[1:-1] * 16 + c[2:], minlength=TRIGRAMS)
        np.log1p(out[:TRIGRAMS], out=out[:TRIGRAMS])
    words, lines = text.split(), [x for x in text.split("\n") if x.strip()]
    n = max(len(words), 1)
    pairs = set(zip(words, words[1:], strict=False))
    marks = (
        min(np.log2(1 + len(raw)) / 16, 1),
        min(len(set(words)) / n * min(1, np.log2(1 + n) / 10 + 0.3), 1),
        1 - len(pairs) / max(n - 1, 1),
        sum(a == b for a, b in zip(words, words[1:], strict=False)) / n,
        1 - len(set(lines)) / max(len(lines), 1),
        min(len(raw) / n / 24, 1),
    )
    for m, value in enumerate(marks):
        # a mark lies between two places and is shared by them, so near values stay near
        at = float(np.clip(value, 0, 1)) * (STEPS - 1)
        low = int(at)
        out[TRIGRAMS + m * STEPS + low] += 1 - (at - low)
        if low + 1 < STEPS:
            out[TRIGRAMS + m * STEPS + low + 1] += at - low
    return out


@dataclass
class Model:
    weight: np.ndarray  # of terms
    axes: np.ndarray  # terms x rank
    vectors: np.ndarray  # labelled x rank, unit length
    labels: np.ndarray
    prior: float
    neighbours: int
    power: float

    def latent(self, counts: np.ndarray) -> np.ndarray:
        v = (counts * self.weight) @ self.axes
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)

    def score(self, counts: np.ndarray) -> np.ndarray:
        """Votes of the nearest labelled vectors; texts without terms get the prior."""
        out = np.full(len(counts), self.prior)
        if not len(self.labels):
            return out
        cos = self.latent(counts) @ self.vectors.T
        k = min(self.neighbours, cos.shape[1])
        near = np.argpartition(cos, -k, axis=1)[:, -k:]
        got = np.take_along_axis(cos, near, 1)
        w = np.maximum(got, 0).astype(np.float64) ** self.power
        whole, up = w.sum(1), (w * self.labels[near]).sum(1)
        last = got.min(1)
        # vectors that tie with the last neighbour share its places, whichever of them were picked
        for r in np.flatnonzero((cos >= last[:, None]).sum(1) > k):
            tied, places = cos[r] == last[r], got[r] == last[r]
            weight = max(float(last[r]), 0.0) ** self.power * places.sum()
            up[r] += weight * self.labels[tied].mean() - (w[r] * self.labels[near[r]])[places].sum()
        some = (counts[:, :TRIGRAMS].any(1)) & (whole > 0)
        out[some] = (up / np.maximum(whole, 1e-300))[some]
        return np.clip(out, 0, 1)


def randomised_axes(x: np.ndarray, rank: int, seed: int = 7, rounds: int = 3) -> np.ndarray:
    """Right singular directions of x by subspace iteration, scaled to even out the leading ones."""
    rank = max(1, min(rank, *x.shape))
    q = np.linalg.qr(x.T @ (x @ np.random.default_rng(seed).standard_normal((x.shape[1], rank + 8)).astype(np.float32)))[0]
    for _ in range(rounds):
        q = np.linalg.qr(x.T @ (x @ q))[0]
    _, s, vt = np.linalg.svd(x @ q, full_matrices=False)
    return ((q @ vt.T)[:, :rank] / np.sqrt(np.maximum(s[:rank], 1e-6))).astype(np.float32)


def document_frequencies(docs: DataFrame, text_col: str = "text") -> tuple[int, np.ndarray]:
    """Rows and document frequencies of the terms over all documents; each partition sends one row a term."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(TERMS + 1, np.int64)
        for b in batches:
            for t in texts_of(b.column("t")):
                total[:TERMS] += term_counts(t) > 0
            total[TERMS] += b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(TERMS + 1, dtype=np.int32)), pa.array(total)], names=["term", "n"])

    got = docs.select(F.col(text_col).alias("t")).mapInArrow(counted, "term int, n long").where("n > 0").groupBy("term").agg(F.sum("n").alias("n")).collect()
    df = np.zeros(TERMS + 1)
    for term, n in got:
        df[term] = n
    return int(df[TERMS]), df[:TERMS]


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", max_labelled: int = 4_000, rank: int = 64, neighbours: int = 24, power: float = 12.0) -> Model:
    """Learns from at most ``max_labelled`` labelled rows that are not held out, the first by a hash of doc_id."""
    n, df = document_frequencies(docs)
    weight = (np.log((1 + n) / (1 + df)) + 0.3).astype(np.float32)
    rows = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.avg(label).alias("y"))
    chosen = rows.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, v = [], []
            for t in texts_of(b.column("t")):
                c = term_counts(t)
                at.append(np.flatnonzero(c).astype(np.uint16).tobytes())
                v.append(c[c != 0].astype(np.float16).tobytes())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("y"), pa.array(at, pa.binary()), pa.array(v, pa.binary())], names=["doc_id", "y", "at", "v"])

    found = docs.select("doc_id", F.col("text").alias("t")).join(F.broadcast(chosen), "doc_id").select("doc_id", "y", "t").mapInArrow(counted, "doc_id long, y double, at binary, v binary")
    # of rows that repeat an id one text is learned from, so that the driver never holds more than max_labelled
    found = sorted(found.groupBy("doc_id").agg(F.first("y").alias("y"), F.min(F.struct("at", "v")).alias("x")).select("doc_id", "y", "x.at", "x.v").collect())
    if not found:
        return Model(weight, np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), np.zeros(0), 0.5, neighbours, power)
    # one matrix of the sample, changed in place: the driver holds max_labelled rows of floats and no copies
    x, y = np.zeros((len(found), TERMS), np.float32), np.array([r["y"] for r in found])
    for row, r in zip(x, found, strict=True):
        row[np.frombuffer(r["at"], np.uint16)] = np.frombuffer(r["v"], np.float16)
    del found
    x *= weight
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    axes = randomised_axes(x, rank)
    vectors = x @ axes
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
    return Model(weight, axes, vectors, y, float(y.mean()), neighbours, power)


def score(docs: DataFrame, model: Model, keep: list[str], text_col: str = "text", block: int = 128, name: str = "score") -> DataFrame:
    """``keep`` columns and the score, called ``name``. Null, empty and term-less texts score the sample's mean label."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = docs.select(*keep).withColumn(name, F.lit(0.0)).schema
    given = text_col if text_col in keep else unused([*keep, name], "text_")[0]

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            texts, got = b.column(given), [np.zeros(0)]
            for at in range(0, len(texts), block):
                got.append(m.score(np.stack([term_counts(t) for t in texts.slice(at, block).to_pylist()])))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), pa.array(np.concatenate(got))], names=[*keep, name])

    rows = docs.select(*keep) if given == text_col else docs.select(*keep, F.col(text_col).alias(given))
    return rows.mapInArrow(scored, schema)


def op9_neighbour_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = score(docs, fit(docs, table(spark, sf_dir, "labels")), ["doc_id"])
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def quality_kept(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier doesn't reject (score of 0.7 or more), with their own columns."""
    name = unused(docs.columns, "quality_score_")[0]
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")), docs.columns, name=name)
    return scored.where(F.col(name) >= 0.7).select(*docs.columns)
