"""Secret scans with multipart credential linking, in DataFrame functions only.

Positions come from the lengths of the pieces between matches, summed by a window over each document's
matches. Strong kinds (assign, access, hex) are always spans. Weak kinds (ident, opaque, endpoint) become
spans only beside a part that completes them: an identifier or an endpoint beside a secret, a secret beside
either. Parts are two spans that do not overlap, with a gap of at most ``scope`` code points. The interval
join is a sweep over the spans' ends, so no pairs are emitted however many candidates a document holds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.llm.common import table

#: Kind, pattern, group whose length counts, least length, role, strong.
KINDS = (
    ("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 8, "secret", True),
    ("access", r"AKIA[A-Z0-9]{12,}", 0, 16, "ident", True),
    ("hex", r"[0-9a-f]{32,}", 0, 32, "secret", True),
    ("ident", r"""(?i:client_?id|access_?key_?id|account_?id|user_?name|login)["']?\x20*[:=]\x20*["']?([A-Za-z0-9_.@-]+)""", 1, 4, "ident", False),
    ("opaque", r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{24,}+", 0, 24, "secret", False),
    ("endpoint", r"""(?i:https?|postgres(?:ql)?|mysql|mongodb|redis|amqps?|s3)://[^\x00-\x20"'<>]+""", 0, 10, "endpoint", False),
)
#: What a match must hold beyond its length.
MUST = {"opaque": "[0-9]"}
#: The roles that complete a role.
COMPLETES = {"ident": ("secret",), "endpoint": ("secret",), "secret": ("ident", "endpoint")}
ORDER = {k[0]: i for i, k in enumerate(KINDS)}


def _found(text: Column, kind: str, pattern: str, group: int) -> Column:
    """array<struct<kind, i, gap, width, inner>> of a kind's leftmost non-overlapping matches."""
    p = F.lit(pattern)
    hits = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, p, F.lit(0)).alias("whole"), F.regexp_extract_all(text, p, F.lit(group)).alias("inner"))
    size = lambda x: F.when(x["whole"].rlike(MUST[kind]), F.length(x["inner"])).otherwise(0) if kind in MUST else F.length(x["inner"])
    some = F.transform(
        F.filter(hits, lambda x: x["whole"].isNotNull()),
        lambda x, i: F.struct(F.lit(ORDER[kind]).alias("kind"), i.alias("i"), F.length(x["gap"]).alias("gap"), F.length(x["whole"]).alias("width"), size(x).alias("inner")),
    )
    return F.when(text.rlike(pattern), some).otherwise(F.array().cast("array<struct<kind:int,i:int,gap:int,width:int,inner:int>>"))


def spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", scope: int = 200) -> DataFrame:
    """(rid, id, kind, start, stop): spans in code points, end exclusive; a row with null kind for a text without any.

    Null and empty texts have none; repeated rows are scanned each; spans of different kinds may overlap."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("id"), text.alias("t"))
    rows = base.select("rid", "id", F.explode_outer(F.concat(*(_found(F.col("t"), k, p, g) for k, p, g, *_ in KINDS))).alias("m")).select("rid", "id", "m.*")
    stop = F.sum(F.col("gap") + F.col("width")).over(W.partitionBy("rid", "kind").orderBy("i").rowsBetween(W.unboundedPreceding, 0))
    # matches that are too short lose their kind, not their row: a document of nothing else keeps one
    least = F.element_at(F.array(*(F.lit(k[3]) for k in KINDS)), F.col("kind") + 1)
    placed = rows.withColumn("stop", stop).select("rid", "id", *(F.when(F.col("inner") >= least, x).alias(n) for n, x in (("kind", F.col("kind")), ("start", F.col("stop") - F.col("width")), ("stop", F.col("stop")))))
    weak = [i for i, k in enumerate(KINDS) if not k[5]]
    # each span is told at its start and at its stop; an end that falls on a start comes before it
    ends = placed.select("rid", "id", "kind", "start", "stop", F.explode(F.array(F.lit(1), F.lit(0))).alias("begins")).withColumn("at", F.when(F.col("begins") == 1, F.col("start")).otherwise(F.col("stop")))
    before = W.partitionBy("rid").orderBy("at", "begins").rowsBetween(W.unboundedPreceding, 0)
    after = W.partitionBy("rid").orderBy(F.col("at").desc(), F.col("begins").desc()).rowsBetween(W.unboundedPreceding, 0)

    def beside(role: str) -> Column:
        """Whether a span of ``role`` ended or begins within scope of this row's end."""
        of = F.col("kind").isin([ORDER[k[0]] for k in KINDS if k[4] == role])
        last = F.max(F.when(of & (F.col("begins") == 0), F.col("at"))).over(before)
        first = F.min(F.when(of & (F.col("begins") == 1), F.col("at"))).over(after)
        return F.coalesce(F.when(F.col("begins") == 1, F.col("at") - last <= scope).otherwise(first - F.col("at") <= scope), F.lit(False))

    told = ends.withColumns({f"by_{r}": beside(r) for r in COMPLETES})
    linked = F.lit(False)
    for i, k in enumerate(KINDS):
        met = F.lit(False)
        for r in COMPLETES[k[4]]:
            met = met | F.col(f"by_{r}")
        linked = F.when(F.col("kind") == i, met).otherwise(linked)
    spans_ = told.groupBy("rid", "id", "kind", "start", "stop").agg(F.max(linked).alias("linked"))
    keep = ~F.col("kind").isin(weak) | F.col("linked")
    # a row without spans stays, so that each document has one
    return spans_.select("rid", "id", F.when(keep, F.col("kind")).alias("kind"), F.when(keep, F.col("start")).alias("start"), F.when(keep, F.col("stop")).alias("stop"))


def op8_secret_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = spans(table(spark, sf_dir, "documents"))
    name = F.element_at(F.array(*(F.lit(k[0]) for k in KINDS)), F.col("kind") + 1)
    one = F.when(F.col("kind").isNotNull(), F.struct("start", "kind", F.concat_ws(":", name, "start", "stop").alias("s")))
    strong = [i for i, k in enumerate(KINDS) if k[5]]
    every = F.sort_array(F.collect_list("one"))
    joined = lambda only: F.array_join(F.transform(F.filter(F.col("l"), lambda x: x["kind"].isin(only)), lambda x: x["s"]), ",")
    out = found.select("rid", "id", "kind", one.alias("one")).groupBy("rid", "id").agg(every.alias("l"), *(F.sum((F.coalesce(F.col("kind"), F.lit(-1)) == i).cast("long")).alias(f"n_{KINDS[i][0]}") for i in strong))
    return out.select(F.col("id").alias("doc_id"), "n_assign", "n_access", "n_hex", F.sha2(joined(strong), 256).alias("base_sha256"), joined(list(range(len(KINDS)))).alias("spans"))
