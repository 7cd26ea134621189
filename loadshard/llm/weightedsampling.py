"""Document fingerprints by consistent weighted sampling, in DataFrame functions only.

Terms are a text's lower-cased words, weights their counts. For term x of weight w and sample k, with
r, c ~ Gamma(2, 1) and b ~ U(0, 1) drawn from hashes of (x, k): t = floor(ln w / r + b) and
ln a = ln c - r (t - b + 1); the sample is the (x, t) of the least ln a. Since ln a is a function of (x, t, k), its
own bits stand for the sample: two texts agree in a lane with the probability of their generalised Jaccard
similarity, sum of least over sum of greatest weights. A lane keeps 16 bits of the hashed minimum.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from loadshard.llm.common import lower_ascii, materialize, table, words_of

SAMPLES = 64
LANE = 4  # hexadecimal digits
MAX_CELLS = 100_000  # neighbour cells; the places where they begin are broadcast, at most 2 MB
CELL_ROWS = 1_000


GRID = 4_096


def _tables() -> tuple[list[float], list[float], list[float]]:
    """At i / GRID for i = 0..GRID: the Gamma(2, 1) quantile and its logarithm; open ends are closed half a step in."""

    def quantile(u: float) -> float:
        lo, hi = 0.0, 50.0
        for _ in range(80):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if 1 - (1 + mid) * math.exp(-mid) < u else (lo, mid)
        return hi

    q = [quantile(min(max(i, 0.5), GRID - 0.5) / GRID) for i in range(GRID + 1)]
    return q, [math.log(x) for x in q]


def with_tables(terms: DataFrame) -> DataFrame:
    """Adds the quantile tables rq and cq (GRID + 1 doubles each, 65 kB in all) to every row by a broadcast of one row."""
    q, lq = _tables()
    doubles = T.ArrayType(T.DoubleType(), False)
    one = terms.sparkSession.createDataFrame([(0, q, lq)], T.StructType([T.StructField("one_", T.LongType(), False), T.StructField("rq", doubles, False), T.StructField("cq", doubles, False)]))
    return terms.withColumn("one_", F.pmod(F.coalesce("term", F.lit(0).cast("long")), F.lit(1).cast("long"))).join(F.broadcast(one), "one_").drop("one_")


def _log_a(term: Column, log_w: Column, k: int) -> Column:
    """ln a of a hashed term. One hash gives r (the middle quantile of one of GRID steps), ln c (interpolated between
    two) and b; in the lowest step of c, where minima of long texts lie, c is drawn from a second hash by the leading
    terms of the quantile, the root of twice the probability plus a third of that."""
    h = F.xxhash64(term, F.lit(k))
    part = lambda at, bits: F.shiftrightunsigned(h, at).bitwiseAND(F.lit((1 << bits) - 1))
    i = part(12, 12).cast("int")
    low = F.get("cq", i)
    between = low + (part(24, 14) + F.lit(0.5)) * F.lit(1.0 / (1 << 14)) * (F.get("cq", i + F.lit(1)) - low)
    u = (F.shiftrightunsigned(F.xxhash64(term, F.lit(k), F.lit(1)), 11) + F.lit(0.5)) * F.lit(2.0 / GRID / (1 << 53))
    c = F.when(i == 0, F.log(F.sqrt(u) + u * F.lit(1 / 3))).otherwise(between)
    r, b = F.get("rq", part(0, 12).cast("int")), (part(38, 24) + F.lit(0.5)) * F.lit(1.0 / (1 << 24))
    return c - r * (F.floor(log_w / r + b) - b + F.lit(1.0))


def minima(terms: DataFrame, keys: list[str], samples: int = SAMPLES) -> DataFrame:
    """keys, m0.. from rows (keys, term long hash or null, w double): the least ln a of each sample, null without terms."""
    logs = with_tables(terms.withColumn("lw", F.log("w")))
    return logs.groupBy(*keys).agg(*[F.min(F.when(F.col("term").isNotNull(), _log_a(F.col("term"), F.col("lw"), k))).alias(f"m{k}") for k in range(samples)])


def lanes(least: list[Column]) -> Column:
    """The fingerprint: LANE digits of each hashed minimum, zeros where there is none."""
    return F.concat(*(F.when(m.isNull(), F.lit("0" * LANE)).otherwise(F.substring(F.lpad(F.hex(F.xxhash64(m)), 16, "0"), 1, LANE)) for m in least))


def likeness(a: Column, b: Column, samples: int = SAMPLES) -> Column:
    """Share of equal lanes."""
    same = F.aggregate(F.sequence(F.lit(0), F.lit(samples - 1)), F.lit(0), lambda n, k: n + (a.substr(k * LANE + 1, F.lit(LANE)) == b.substr(k * LANE + 1, F.lit(LANE))).cast("int"))
    return same / F.lit(float(samples))


def _tagged(text: Column, tag: int) -> Column:
    return F.transform(words_of(lower_ascii(text)), lambda x: F.shiftleft(F.xxhash64(x), 1).bitwiseOR(F.lit(tag)))


def weighted_terms(rows: DataFrame, keys: list[str], first: Column, second: Column | None = None) -> DataFrame:
    """(keys, side, term, w): hashed words with their counts, of one text or of two.

    side 0: of the first text, 1: of the second, 2: of both with one count, so that a term common to two versions of a
    text is sampled once. A row with a null term tells a text without words. Counting stays in the row: equal hashes
    stand together in the sorted array, the side in their last bit, and a count is the distance between first places."""
    both = _tagged(first, 0) if second is None else F.concat(_tagged(first, 0), _tagged(second, 1))
    hashed = rows.select(*keys, F.sort_array(both).alias("h"))
    start = F.filter(F.sequence(F.lit(0), F.size("h") - 1), lambda i: (i == 0) | (F.get("h", i) != F.get("h", i - 1)))
    places = hashed.select(*keys, "h", F.when(F.size("h") > 0, start).alias("p"))
    runs = places.select(*keys, F.transform("p", lambda at, j: F.struct(F.get("h", at).alias("h"), (F.coalesce(F.get("p", j + 1), F.size("h")) - at).alias("n"))).alias("x"))

    def twin(x: Column, j: Column, step: int) -> Column:
        y = F.get("x", j + step)
        return (y["h"] == x["h"].bitwiseXOR(F.lit(1))) & (y["n"] == x["n"])

    tag = lambda x: x["h"].bitwiseAND(F.lit(1)).cast("int")
    has = lambda x, j, step: F.coalesce(twin(x, j, step), F.lit(False))
    side = lambda x, j: F.when(tag(x) == 0, F.when(has(x, j, 1), 2).otherwise(0)).otherwise(F.when((j > 0) & has(x, j, -1), -1).otherwise(1))
    told = F.transform("x", lambda x, j: F.struct(x["h"].alias("h"), x["n"].alias("n"), side(x, j).alias("side")))
    sides = F.filter(told, lambda x: x["side"] >= 0)
    return runs.select(*keys, F.explode_outer(sides).alias("x")).select(*keys, F.coalesce("x.side", F.lit(2)).alias("side"), F.shiftright("x.h", 1).alias("term"), F.col("x.n").cast("double").alias("w"))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES) -> DataFrame:
    """(id, fp) for every row; null and blank texts get the zero fingerprint, equal texts equal ones."""
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("id"), F.col(text_col).alias("t"))
    least = minima(weighted_terms(rows, ["rid", "id"], F.col("t")), ["rid", "id"], samples)
    return least.select("id", lanes([F.col(f"m{k}") for k in range(samples)]).alias("fp"))


def _places(base: DataFrame) -> DataFrame:
    """Adds place, which orders rows by descending id, nulls last, then by a hash of the text."""
    return base.withColumn("place", F.struct(F.col("id").isNull().cast("int").alias("last"), F.coalesce(F.bitwise_not("id"), F.lit(0)).alias("down"), F.xxhash64("t").alias("h")))


def _cell_starts(base: DataFrame) -> DataFrame:
    """One row: the places at which cells of about CELL_ROWS rows begin, in order, whatever the ids' spread.

    Spark's range partitioning picks them from its sample; ids that repeat are told apart by their texts' hashes, so
    no id makes a cell of its own."""
    places = _places(base).select("place")
    cells = max(1, min(MAX_CELLS, places.count() // CELL_ROWS))
    firsts = places.repartitionByRange(cells, "place").groupBy(F.spark_partition_id().alias("p")).agg(F.min("place").alias("place"))
    return firsts.agg(F.sort_array(F.collect_list("place")).alias("starts"))


def _with_next(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(cell, place, id, t, own): documents dealt into cells of neighbours, each cell ending with a copy of the next
    cell's first document (own = false), so that a neighbour never lies in another cell."""
    base = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    starts = materialize(_cell_starts(base))
    n = F.size("starts")
    steps = F.array(*(F.lit(1 << k) for k in reversed(range(MAX_CELLS.bit_length()))))
    # the last start that is not behind a row's place, by bisection
    at = F.aggregate(steps, F.lit(0), lambda lo, step: F.when((lo + step < n) & (F.get("starts", lo + step) <= F.col("place")), lo + step).otherwise(lo))
    placed = _places(base).withColumn("one", F.lit(1)).join(F.broadcast(starts.withColumn("one", F.lit(1))), "one").withColumn("cell", at)
    # a cell's first rows are told once more, to the cell before (the first cell's to the last)
    first = F.get("starts", F.col("cell")) == F.col("place")
    to = F.array(F.struct(F.col("cell"), F.lit(True).alias("own")), F.struct(F.pmod(F.col("cell") - 1, n).alias("cell"), F.lit(False).alias("own")))
    return placed.select("place", "id", "t", F.explode(F.slice(to, F.lit(1), F.when(first, 2).otherwise(1))).alias("x")).select("x.cell", "place", "id", "t", "x.own")


def edited_pairs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES) -> DataFrame:
    """Per row: id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The last third of a text (rounded down) is replaced by as many first code points of the next document in
    descending id, the last one's next being the first. Null texts are empty; of rows that share an id, order is
    by a hash of the text; a single document is its own next."""
    cells = _with_next(docs, id_col, text_col)
    order = W.partitionBy("cell").orderBy(F.col("own").desc(), "place")
    n = F.length("t")
    third = F.floor(n / 3).cast("int")
    # rows keep the cell's partitioning from here on: nothing below is shuffled again
    seen = cells.select("cell", "own", F.row_number().over(order).alias("pos"), "id", "t", F.lead("t").over(order).alias("nxt"))
    edited = F.concat(F.substring(F.col("t"), F.lit(1), n - third), F.coalesce(F.substring(F.col("nxt"), F.lit(1), third), F.lit("")))
    keys = ["cell", "pos", "own", "id", "n_chars", "sha"]
    both = seen.select("cell", "pos", "own", "id", n.cast("long").alias("n_chars"), "t", edited.alias("e")).withColumn("sha", F.sha2("e", 256))
    least = minima(weighted_terms(both, keys, F.col("t"), F.col("e")), [*keys, "side"], samples)
    # each side's minima, then the least of a version's own and the shared ones
    of = lambda without: [F.min(F.when(F.col("side") != without, F.col(f"m{k}"))) for k in range(samples)]
    two = least.groupBy(*keys).agg(F.array(*of(1)).alias("a"), F.array(*of(0)).alias("b"))
    two = two.select(*keys, lanes([F.get("a", k) for k in range(samples)]).alias("fp"), lanes([F.get("b", k) for k in range(samples)]).alias("efp"))
    nxt = F.lead("fp").over(W.partitionBy("cell").orderBy("pos"))
    return two.withColumn("nfp", nxt).where("own").select(
        "id", "n_chars", F.col("sha").alias("edited_sha256"), F.col("fp").alias("fingerprint"), F.col("efp").alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("efp"), samples).alias("near_edited"), likeness(F.col("fp"), F.coalesce("nfp", "fp"), samples).alias("near_next"),
    )


def op1_weighted_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_pairs(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")
