"""Benchmark decontamination by latent semantic retrieval.

Benchmark passages become TF-IDF vectors whose document frequencies come from all documents. They are indexed in
blocks, each with latent axes of its own: as many as leave every passage KEPT of its norm, so that a copy of a passage
is near it however many passages there are. Windows of documents are projected through the axes of each block and meet
its passages in exact blocked cosine products; candidates are then checked by the longest common
subsequence of words, over the passage and over its answer (the last quarter of the passage).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from loadshard.llm.common import materialize, table, texts_of, unused

WORDS = re.compile(r"\w+")
WINDOWS = (16, 32, 64)
MAX_PASSAGE = 64
#: About how many passages an index has; more are indexed and searched slice by slice.
MAX_PASSAGES = 200_000
#: Passages of a block, the least share of a passage's norm that its axes hold, and bytes of blocks broadcast at once.
BLOCK, KEPT = 256, 0.7
PART_BYTES = 256 << 20
RARE, FEW = 8, 20
COMMON, OTHER = -2, -1
NONE = (None, 0.0, 0.0, 0.0)


def words(text: str | None) -> list[str]:
    return WORDS.findall(text.lower()) if text else []


def passages(text: str | None) -> list[list[str]]:
    """Word runs of at most MAX_PASSAGE words, of nearly equal length."""
    w = words(text)
    n = -(-len(w) // MAX_PASSAGE)
    return [w[len(w) * i // n : len(w) * (i + 1) // n] for i in range(n)]


def lcs_length(a: list[str], b: list[str]) -> int:
    """Longest common subsequence, a row of the table at a time as bits of one integer."""
    where: dict[str, int] = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for x in b:
        if m := where.get(x):
            u = row & m
            row = ((row + u) | (row - u)) & full
    return len(a) - row.bit_count()


@dataclass
class Block:
    terms: np.ndarray  # numbers of the terms of its passages, ascending
    vectors: np.ndarray  # its terms x rank, weighted
    passages: np.ndarray  # its passages x rank, unit length


@dataclass
class Index:
    term: dict[str, int]  # benchmark words: rare ones and the rarest of each passage have numbers, others COMMON
    energy: np.ndarray  # squared weight of each term, then of COMMON and OTHER words
    rows: list[tuple[list[int], list[float]]]  # terms and weights of each passage, unit length
    words: list[list[str]]
    item: np.ndarray
    rank: int


@dataclass
class Part:
    """What is broadcast at once: some blocks, and the words and items of their passages, in order."""

    term: dict[str, int]
    energy: np.ndarray
    blocks: list[Block]
    words: list[list[str]]
    item: np.ndarray


def corpus_frequencies(docs: DataFrame, vocabulary: set[str], text_col: str) -> tuple[int, Counter]:
    """Rows, and in how many of them each benchmark word occurs."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n: Counter = Counter()
        for b in batches:
            for t in texts_of(b.column("t")):
                n.update(vocabulary.intersection(words(t)))
            n[""] += b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64())], names=["term", "n"])

    rows = docs.select(F.col(text_col).alias("t")).mapInArrow(counted, "term string, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    n = Counter({r[0]: r[1] for r in rows})  # one number for each word of the benchmark
    return n.pop("", 0), n


def build(docs: DataFrame, benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", rank: int = 128, common: float = 0.05) -> Index | None:
    """Index of all passages of a benchmark, or of a slice of one, held by the driver.

    Words in more than ``common`` of the documents (and in more than FEW) count only as one of a passage's RARE rarest."""
    items = benchmark.select(id_col, text_col).collect()
    got = [(r[0], p) for r in sorted(items, key=lambda r: (r[0] is None, r[0] or 0, r[1] or "")) for p in passages(r[1])]
    if not got:
        return None
    vocabulary = {w for _, p in got for w in p}
    n, df = corpus_frequencies(docs, vocabulary, text_col)
    keep = {w for w in vocabulary if df[w] <= max(common * n, FEW)}
    for _, p in got:
        keep.update(sorted(set(p), key=lambda w: (df[w], w))[:RARE])
    term = {w: i for i, w in enumerate(sorted(keep))}
    idf = np.array([np.log((1 + n) / (1 + df[w])) + 1 for w in term])
    rows = []
    for _, p in got:
        c = Counter(term[w] for w in p if w in term)
        v = np.array([k * idf[i] for i, k in c.items()])
        rows.append((list(c), (v / np.linalg.norm(v)).tolist()))
    energy = np.concatenate([idf**2, [0.0, (np.log(1 + n) + 1) ** 2 / 2]])
    term |= dict.fromkeys(vocabulary - keep, COMMON)
    return Index(term, energy, rows, [p for _, p in got], np.array([-1 if i is None else i for i, _ in got], np.int64), rank)


def slices(docs: DataFrame, benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", **more) -> Iterator[Index | None]:
    """Indexes of a benchmark of any size: items are dealt by a hash to slices of about half MAX_PASSAGES passages."""
    words_ = F.coalesce(F.regexp_count(text_col, F.lit(r"(?U)\w+")), F.lit(0))
    total = benchmark.agg(F.sum(F.ceil(words_ / MAX_PASSAGE))).first()[0] or 0
    n = max(1, -(-2 * total // MAX_PASSAGES)) if total > MAX_PASSAGES else 1
    for k in range(n):
        part = benchmark if n == 1 else benchmark.where(F.pmod(F.xxhash64(id_col, text_col), F.lit(n)) == k)
        yield build(docs, part, id_col, text_col, **more)


def block_of(index: Index, lo: int, hi: int) -> Block:
    """Passages lo to hi with the index' rank, or the higher one at which each keeps KEPT of its norm."""
    rows = index.rows[lo:hi]
    terms = np.unique(np.concatenate([i for i, _ in rows]).astype(np.int64))
    x = np.zeros((len(rows), len(terms)))
    for k, (i, w) in enumerate(rows):
        x[k, np.searchsorted(terms, i)] = w
    power, left = np.linalg.eigh(x @ x.T)
    power, left = power[::-1], left[:, ::-1]
    full = max(1, int((power > 1e-9).sum()))
    held = np.cumsum(left[:, :full] ** 2 * power[:full], axis=1).min(0)
    rank = min(full, max(index.rank, int(np.searchsorted(held, KEPT**2)) + 1))
    axes = x.T @ (left[:, :rank] / np.sqrt(power[:rank]))
    vec = x @ axes
    vec /= np.maximum(np.linalg.norm(vec, axis=1), 1e-9)[:, None]
    return Block(terms, (axes * np.sqrt(index.energy[terms])[:, None]).astype(np.float32), vec.astype(np.float32))


def parts_of(index: Index) -> Iterator[Part]:
    """The whole index in parts of about PART_BYTES, each made when it is asked for."""
    first, size, blocks = 0, 0, []
    for lo in range(0, len(index.rows), BLOCK):
        hi = min(lo + BLOCK, len(index.rows))
        blocks.append(block_of(index, lo, hi))
        size += blocks[-1].vectors.nbytes + blocks[-1].passages.nbytes
        if size >= PART_BYTES or hi == len(index.rows):
            yield Part(index.term, index.energy, blocks, index.words[first:hi], index.item[first:hi])
            first, size, blocks = hi, 0, []


def candidates(part: Part, ids: np.ndarray, least: float) -> list[tuple[int, int, int, float]]:
    """(start, end, passage, cosine) of windows of a text; ids: term of each word, COMMON or OTHER.

    A window's length counts all its words, those that no passage has as rare ones. The share of it that a block's terms
    hold bounds the cosine, so only windows with enough of it are projected."""
    weight = part.energy[ids]
    total = np.concatenate(([0.0], np.cumsum(weight)))
    known = np.flatnonzero(ids >= 0)
    spans = []
    for size in WINDOWS:
        start = np.arange(0, max(1, len(ids) - size // 2), size // 2)
        end = np.minimum(start + size, len(ids))
        spans.append((start, end, np.maximum(total[end] - total[start], 1e-9)))
    out, first = [], 0
    for b in part.blocks:
        at = np.minimum(np.searchsorted(b.terms, ids[known]), len(b.terms) - 1)
        mine = b.terms[at] == ids[known]
        met, local = known[mine], at[mine]
        held = np.concatenate(([0.0], np.cumsum(weight[met])))
        for start, end, whole in spans:
            lo, hi = np.searchsorted(met, start), np.searchsorted(met, end)
            use = np.flatnonzero((hi > lo) & (held[hi] - held[lo] >= least * least * whole))
            for block in range(0, len(use), 1024):
                u = use[block : block + 1024]
                v = np.stack([b.vectors[local[i:j]].sum(0) for i, j in zip(lo[u], hi[u], strict=True)])
                cos = (v @ b.passages.T) / np.sqrt(whole[u])[:, None]
                r, c = np.nonzero(cos >= least)
                out += [(int(start[u[i]]), int(end[u[i]]), first + int(j), float(cos[i, j])) for i, j in zip(r, c, strict=True)]
        first += len(b.passages)
    return out


def leaked(share, answer, cosine):
    """A passage is leaked at seven tenths of its words in order, or at 55 % with most of its answer in a close window."""
    return (share >= 0.7) | ((share >= 0.55) & (answer >= 0.75) & (cosine >= 0.45))


def judge(index: Part, w: list[str], found: list[tuple[int, int, int, float]], best: tuple = NONE) -> tuple[int | None, float, float, float]:
    """(item, cosine, share of the passage, share of its answer) of the passage best supported by the text, or ``best``.

    Leaked passages come before others; a passage's cosine is that of its closest window."""
    close: dict[int, float] = {}
    for *_, j, cos in found:
        close[j] = max(cos, close.get(j, 0.0))
    rank = (leaked(best[2], best[3], best[1]), best[2], best[1])
    seen = set()
    for start, end, j, _ in found:
        p = index.words[j]
        spare = max(0, len(p) - (end - start)) + len(p) // 2
        lo, hi = max(0, start - spare), min(len(w), end + spare)
        if (key := (j, lo // 8, hi // 8)) in seen:
            continue
        seen.add(key)
        piece, cos = w[lo:hi], close[j]
        share = lcs_length(p, piece) / len(p)
        tail = p[-max(1, len(p) // 4) :]
        answer = lcs_length(tail, piece) / len(tail) if share >= 0.55 or (share, cos) > rank[1:] else 0.0
        if (now := (leaked(share, answer, cos), share, cos)) > rank:
            rank, best = now, (int(index.item[j]), cos, share, answer)
    return best


TOLD = ("item_", "cosine_", "lcs_", "answer_")


def search(docs: DataFrame, index: Index | None | Iterable[Index | None], keep: list[str], text_col: str = "text", least: float = 0.35) -> DataFrame:
    """``keep`` columns, item_, cosine_, lcs_ and answer_ (with further underscores where ``keep`` has such names) of the
    best passage for every row (null item: no candidate), over one index or several.

    Null and empty texts have none. Leaked passages come first; of equally supported ones the one met first is told."""
    told = unused(keep, *TOLD)
    blank = dict(zip(told, (F.lit(None).cast("long"), F.lit(0.0), F.lit(0.0), F.lit(0.0)), strict=True))
    given = text_col if text_col in keep else unused([*keep, *told], "text_")[0]
    rows = docs.select(*keep) if given == text_col else docs.select(*keep, F.col(text_col).alias(given))
    schema = rows.withColumns(blank).schema
    every = [index] if index is None or isinstance(index, Index) else index
    first = True
    for part in (p for x in every if x is not None for p in parts_of(x)):
        shared = docs.sparkSession.sparkContext.broadcast(part)

        def searched(batches: Iterator[pa.RecordBatch], shared=shared, again=not first) -> Iterator[pa.RecordBatch]:
            x = shared.value
            get = x.term.get
            for b in batches:
                got = []
                before = zip(*(b.column(c).to_pylist() for c in told), strict=True) if again else repeat(NONE)
                for t, best in zip(texts_of(b.column(given)), before):
                    w = words(t)
                    ids = np.fromiter(map(get, w, repeat(OTHER)), np.int64, len(w))
                    got.append(judge(x, w, candidates(x, ids, least), best) if (ids >= 0).any() else best)
                item, *rest = zip(*got, strict=True) if got else ((), (), (), ())
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in schema.names[:-4]), pa.array(item, pa.int64()), *(pa.array(r, pa.float64()) for r in rest)], names=schema.names)

        # an index of several parts is searched part by part, the best so far told to the next
        rows = (rows if first else materialize(rows)).mapInArrow(searched, schema)
        first = False
    return (rows.withColumns(blank) if first else rows).select(*keep, *told)


def contaminated(told: Sequence[str] = TOLD) -> Column:
    _, cosine, share, answer = told
    return leaked(F.col(share), F.col(answer), F.col(cosine))


def op7_latent_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = search(docs, slices(docs, table(spark, sf_dir, "benchmark")), ["doc_id"])
    return out.select("doc_id", F.col("item_").alias("item_id"), F.round("cosine_", 4).alias("cosine"), F.round("lcs_", 4).alias("lcs"), F.round("answer_", 4).alias("answer"), contaminated().alias("contaminated"))


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = search(docs, slices(docs, table(spark, sf_dir, "benchmark")), docs.columns)
    return out.where(~contaminated(unused(docs.columns, *TOLD))).select(*docs.columns)
