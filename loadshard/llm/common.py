"""Shared pieces: materialisation in the shared folder, connected components, whole-text helpers."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Word and blank classes of the query contracts.
WORD = r"[^\x20\x09-\x0D]+"
BLANK = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's spark.checkpoint.dir; one of our own only where it is unset."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("loadshard.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="loadshard-")
        spark.conf.set("loadshard.checkpoint.dir", found)
    return found


def materialize(df: DataFrame) -> DataFrame:
    """Cuts lineage by a table in the shared folder; a lost executor costs a reread, not a recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/loadshard-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_to = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes the table of a materialised DataFrame that nothing reads any more."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(df.written_to)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def texts_of(column: pa.Array, step: int = 64) -> Iterator[str | None]:
    """Texts of an Arrow column, a few at a time, so that a batch is never held as Python strings."""
    for at in range(0, len(column), step):
        yield from column.slice(at, step).to_pylist()


def lower_ascii(text: Column) -> Column:
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words_of(text: Column) -> Column:
    """Words of a text (null and blank: an empty array)."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANK), lambda w: w != "")


def unused(columns: list[str], *names: str) -> list[str]:
    """``names``, each with underscores appended until no column is called so (in any case)."""
    taken, out = {c.lower() for c in columns}, []
    for n in names:
        while n.lower() in taken:
            n += "_"
        taken.add(n.lower())
        out.append(n)
    return out


def running_total(rows: DataFrame, keys: list[str], order: str, value: str, name: str, span: int = 4_096) -> DataFrame:
    """``rows`` with ``name``: the sum of ``value`` up to and with each row, by ``keys`` in the order of a whole number.

    Sums of runs of ``span`` numbers come first, so no task meets all rows of a key, only its runs."""
    cut = rows.withColumn("run_", F.floor(F.col(order) / span))
    runs = cut.groupBy(*keys, "run_").agg(F.sum(value).alias("sum_"))
    before = F.sum("sum_").over(W.partitionBy(*keys).orderBy("run_").rowsBetween(W.unboundedPreceding, 0)) - F.col("sum_")
    inside = F.sum(value).over(W.partitionBy(*keys, "run_").orderBy(order).rowsBetween(W.unboundedPreceding, 0))
    told = runs.select(*keys, "run_", before.alias("before_"))
    return cut.withColumn(name, inside).join(told, [*keys, "run_"]).withColumn(name, F.col(name) + F.col("before_")).drop("run_", "before_")


#: Edges that one task settles at once; a run of tasks contracts as many at a time.
ONE_TASK = 2_000_000


def contracted(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, component) of these edges' nodes that are not their component's smallest."""
    names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    parent = np.arange(len(names))
    while len(x):
        np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := parent[parent], parent):
            parent = up
        x, y = parent[x], parent[y]
        x, y = x[x != y], y[x != y]
    left = np.flatnonzero(parent != np.arange(len(names)))
    return names[left], names[parent[left]]


def contracted_edges(edges: DataFrame) -> DataFrame:
    """(a, b): edges to each component's smallest node within runs of a task's edges; no more than the runs have nodes."""

    def batch(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        a, b = (np.concatenate([x.column(c).to_numpy() for x in held]) for c in ("a", "b"))
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in contracted(a, b)], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for x in batches:
            held.append(x)
            size += x.num_rows
            if size >= ONE_TASK:
                yield batch(held)
                held, size = [], 0
        if size:
            yield batch(held)

    return edges.mapInArrow(run, "a long, b long")


def connected_components(edges: DataFrame, max_rounds: int = 40, one_task: int = ONE_TASK) -> DataFrame:
    """(node, component) for every node of ``edges`` (columns a, b); component is its smallest node.

    Each task contracts its edges first. Of whole numbers up to ``one_task`` edges that are left are settled by one task.
    More of them, and other names, alternate the two star contractions, each a partial aggregation and an equi-join, and
    write the remaining edges to the shared folder each round. Self-loops and repeated edges are allowed, null ends are
    ignored, no edges give no rows."""
    e = edges.where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    whole = all(t in ("bigint", "int") for _, t in e.dtypes)
    e = materialize(contracted_edges(e.select(*(F.col(c).cast("long") for c in "ab"))).distinct() if whole else e.distinct())
    if whole and e.count() <= one_task:
        e = materialize(contracted_edges(e.repartition(1)))
    else:
        e = star_rounds(e, max_rounds)
    return e.select(F.col("a").alias("node"), F.col("b").alias("component")).union(e.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def star_rounds(e: DataFrame, max_rounds: int) -> DataFrame:
    """A written table of edges (a, b), b < a, turned into one from each node to its component's smallest."""
    mark = lambda d: tuple(d.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first())
    seen = mark(e)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        before, e = e, materialize(small.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).union(low.select("a", F.col("m").alias("b"))).distinct())
        now = mark(e)
        discard(before)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return e


class Roots:
    """Union-find over names; a class is named by its smallest."""

    def __init__(self, names):
        self.parent = {n: n for n in names}

    def find(self, r):
        parent = self.parent
        while parent[r] != r:
            parent[r] = r = parent[parent[r]]
        return r

    def join(self, r, q) -> None:
        self.parent[max(r, q)] = min(r, q)


def alike(a: frozenset, b: frozenset, threshold: float) -> bool:
    if min(len(a), len(b)) < threshold * max(len(a), len(b)):
        return False
    both = len(a & b)
    return both >= threshold * (len(a) + len(b) - both)


#: Most bits of a sketch.
MOST_BITS = 1 << 17
SKETCH_ROWS = 64


def sketched(sets: list[frozenset]) -> np.ndarray:
    """A row of bits for each set, each the parity of the members that a hash deals to it. The rows of two sets differ in no
    more bits than one of the two sets alone has members; bits are enough for most sets to differ in nearly as many."""
    large = sorted(map(len, sets))[len(sets) * 9 // 10]
    bits = max(64, min(MOST_BITS, 1 << max(8, (2 * large - 1).bit_length())))
    out = np.zeros((len(sets), bits // 64), np.uint64)
    for k, s in enumerate(sets):
        h = np.fromiter(map(hash, s), np.int64, len(s)).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        odd = np.bincount((h >> np.uint64(32)).astype(np.int64) & (bits - 1), minlength=bits) & 1
        out[k] = np.packbits(odd.astype(np.uint8)).view(np.uint64)
    return out


def near_pairs(sizes: np.ndarray, sketches: np.ndarray, left: np.ndarray, right: np.ndarray | None, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of numbers of sets, of left and of right (None: every two of left): all that are alike, and few others.

    Alike sets have like sizes and few members that are not common, so their sketches differ in few bits."""
    left = left[np.argsort(sizes[left], kind="stable")]
    other = left if right is None else right[np.argsort(sizes[right], kind="stable")]
    there, words = sizes[other], np.ascontiguousarray(sketches[other].T)
    for at in range(0, len(left), SKETCH_ROWS):
        rows = left[at : at + SKETCH_ROWS]
        mine = sizes[rows]
        lo = np.searchsorted(there, threshold * mine[0] - 1e-6)
        hi = at + len(rows) if right is None else np.searchsorted(there, mine[-1] / threshold + 1e-6, "right")
        apart = np.zeros((len(rows), hi - lo), np.uint32)
        for a, b in zip(sketches[rows].T, words[:, lo:hi], strict=True):
            apart += np.bitwise_count(a[:, None] ^ b)
        i, j = np.nonzero(apart * (1 + threshold) <= (mine[:, None] + there[lo:hi]) * (1 - threshold) + 1e-6)
        yield rows[i], other[lo + j]


def join_alike(held: list, sets: list[frozenset], left: np.ndarray, right: np.ndarray | None, roots: Roots, threshold: float) -> None:
    """Joins the classes (``held``, by set) of every two alike sets of left and right. Exact: sketches only tell pairs that
    cannot be alike, the others are compared unless they are in one class by then."""
    if not len(left) or right is not None and not len(right):
        return
    sizes = np.array([len(s) for s in sets])
    names = list(dict.fromkeys(held))
    at = {r: k for k, r in enumerate(names)}
    of, label = np.array([at[r] for r in held]), None
    for i, j in near_pairs(sizes, sketched(sets), left, right, threshold):
        if label is None:
            label = np.array([at[roots.find(r)] for r in names])[of]
        unlike = label[i] != label[j]
        for x, y in zip(i[unlike].tolist(), j[unlike].tolist(), strict=True):
            r, q = roots.find(held[x]), roots.find(held[y])
            if r != q and alike(sets[x], sets[y], threshold):
                roots.join(r, q)
                label = None


def cluster_sets(names: list, sets: list[frozenset], threshold: float, few: int = 6) -> list:
    """Class of each set: the smallest name linked to it by Jaccard similarity of at least ``threshold``; exact.

    A few sets are compared pair by pair. More of them first meet one set of the largest class so far, which often leaves
    one class; where it does not, all are compared, but for sets already in one class."""
    roots = Roots(names)
    if len(sets) <= few:
        for j in range(1, len(sets)):
            for i in range(j):
                r, q = roots.find(names[i]), roots.find(names[j])
                if r != q and alike(sets[i], sets[j], threshold):
                    roots.join(r, q)
        return [roots.find(n) for n in names]
    heads = {0: 1}  # a set for each class so far, with how many it met
    for j in range(1, len(sets)):
        head = max(heads, key=heads.__getitem__)
        for i in {head, j - 1}:
            if alike(sets[i], sets[j], threshold):
                roots.join(roots.find(names[i]), roots.find(names[j]))
                heads[head] += i == head
                break
        else:
            if len(heads) < few:
                heads[j] = 1
    if len({roots.find(n) for n in names}) == 1:
        return [roots.find(n) for n in names]
    join_alike([roots.find(n) for n in names], sets, np.arange(len(sets)), None, roots, threshold)
    return [roots.find(n) for n in names]


def merged_sides(names: list, roots: list, sides: list, sets: list[frozenset], threshold: float) -> list:
    """Class of each set after two sides, each clustered before into ``roots``, are compared set by set: the smallest
    root linked to it. Exact."""
    classes = Roots(roots)
    side = np.array(sides, bool)
    join_alike(roots, sets, np.flatnonzero(~side), np.flatnonzero(side), classes, threshold)
    return [classes.find(r) for r in roots]


def classes_in_groups(rows: DataFrame, value: str, fn: Callable[..., list], also: tuple[str, ...] = ()) -> DataFrame:
    """(h, root): ``fn(names, values, *also)`` gives the class of each row of a (group, part) of rows (h, group, part,
    value, *also).

    Groups are read one after the other from sorted partitions, so that many small ones cost no call of their own;
    memory is that of the largest group."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, held = None, [[] for _ in range(2 + len(also))]
        for b in batches:
            g, part, columns = b.column("group").to_numpy(), b.column("part").to_numpy(), [b.column(c) for c in ("h", value, *also)]
            cuts = [0, *(np.flatnonzero((g[1:] != g[:-1]) | (part[1:] != part[:-1])) + 1), len(g)]
            done_names, done_roots = [], []
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                if j == i:
                    continue
                if (g[i], part[i]) != current:
                    done_names += held[0]
                    done_roots += fn(*held) if held[0] else []
                    current, held = (g[i], part[i]), [[] for _ in columns]
                for to, c in zip(held, columns, strict=True):
                    to += c.slice(i, j - i).to_pylist()
            yield pa.RecordBatch.from_arrays([pa.array(done_names, pa.int64()), pa.array(done_roots, pa.int64())], names=["h", "root"])
        if held[0]:
            yield pa.RecordBatch.from_arrays([pa.array(held[0], pa.int64()), pa.array(fn(*held), pa.int64())], names=["h", "root"])

    return rows.select("h", "group", "part", value, *also).repartition("group", "part").sortWithinPartitions("group", "part").mapInArrow(run, "h long, root long")


def classes_in_parts(held: DataFrame, value: str, set_of: Callable[[str], frozenset], threshold: float) -> DataFrame:
    """(h, root) of the rows of a written table (h, group, part, value) whose class has others; exact for each group.

    Parts are clustered alone. In groups of several parts one row of each part's largest cluster meets those of the
    others, which often leaves one class; where it does not, every two parts of the group are compared, row by row."""
    within = lambda names, values: cluster_sets(names, [set_of(x) for x in values], threshold)
    across = lambda names, values, roots, sides: merged_sides(names, roots, sides, [set_of(x) for x in values], threshold)
    found = materialize(classes_in_groups(held, value, within))
    edges = found.where("h <> root").select(F.col("h").alias("a"), F.col("root").alias("b"))
    spans = materialize(held.groupBy("group").agg((F.max("part") + 1).cast("long").alias("parts")).where("parts > 1"))
    if spans.isEmpty():
        return edges.select(F.col("a").alias("h"), F.col("b").alias("root")).union(edges.select("b", "b").distinct())
    places = materialize(held.join(spans, "group").select("h", "group", "part", "parts").hint("merge").join(found, "h"))
    sizes = places.groupBy("group", "part", "root").agg(F.count(F.lit(1)).alias("n"))
    first = sizes.groupBy("group", "part").agg(F.max_by("root", F.struct("n", "root")).alias("h"))
    heads = first.select("h", "group", F.lit(0).cast("long").alias("part")).hint("merge").join(held.select("h", value), "h")
    edges = materialize(edges.union(classes_in_groups(heads, value, within).where("h <> root").select("h", "root")))
    linked = materialize(connected_components(edges))
    labels = places.drop("root").hint("merge").join(linked.select(F.col("node").alias("h"), F.col("component").alias("root")), "h", "left").withColumn("root", F.coalesce("root", "h"))
    labels = materialize(labels)
    open_ = labels.groupBy("group").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low < high").select("group")
    pairs = labels.join(open_, "group", "left_semi").withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1))).where("other <> part")
    pairs = pairs.select("h", "group", (F.least("part", "other") * F.col("parts") + F.greatest("part", "other")).alias("part"), "root", (F.col("part") > F.col("other")).alias("side"))
    # shuffled: Spark takes the pairs to be as few as the labels that were exploded
    more = materialize(classes_in_groups(pairs.hint("merge").join(held.select("h", value), "h"), value, across, ("root", "side")))
    edges = edges.union(more.where("h <> root").select("h", "root"))
    return connected_components(edges).select(F.col("node").alias("h"), F.col("component").alias("root"))
