"""Mixing sources to target weights by hash thresholds.

Each row has a fixed hash. A source takes all its rows ``full`` times, and once more the rows whose hash lies
under the source's threshold. Thresholds come from histograms of tokens by (source, hash bucket): the bucket in which
the budget falls is the only one that is refined, level by level, so nothing is sorted. Thresholds grow with the
budget, hence smaller mixes are nested in larger ones.

Only DataFrame functions are used. The text is read once; the narrow table of sizes is checkpointed. Windows run over
histogram rows (4096 a source at most) and over the table of sources, never over documents.

Defined results: null text has size 0; a null source is a source of its own, last in order; rows with equal ids share a hash
and are taken or left together; a source of size 0 has target 0; an empty table gives no rows. Only the named columns
are read.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .state import checkpointed

WORD = r"[^\x20\x09-\x0D]+"
HASH_BITS = 60
BROADCAST_ROWS = 100_000


def keyed_hash(key: Column) -> Column:
    """60 uniform bits of a key, the same in every engine that has md5."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, HASH_BITS // 4), 16, 10).cast("long")


def beside(sources: DataFrame, most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """A table with a row per source, ready to be joined: broadcast if its counted rows are few, else left to a shuffle whose hot keys are split at run time."""
    return F.broadcast(sources) if sources.count() <= most_rows else sources


def targets(sources: DataFrame, weights: Sequence[int] = (1, 2, 3), share: float = 1.0, most: int = 3) -> DataFrame:
    """(source, source_size, target) from (source, source_size).

    Sources in code point order, null last, weigh ``weights`` repeating and share ``share`` of all sizes; a target stops at ``most`` times its
    source, the excess reshared by weight. With sources ordered by cap a weight, the common level is the largest of the
    levels got by capping the first k, so no iteration is needed.
    """
    at = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (at % len(weights) + 1).cast("int"))
    weighed = sources.withColumn("weight", weight).withColumn("cap", F.col("source_size") * most)
    order = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    after = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.floor(F.sum("source_size").over(every) * F.lit(float(share)))
    level = (total - F.coalesce(F.sum("cap").over(before), F.lit(0))).cast("double") / F.sum("weight").over(after)
    levelled = weighed.withColumn("level", level).withColumn("level", F.max("level").over(every))
    return levelled.select("source", "source_size", F.least(F.col("cap").cast("double"), F.col("level") * F.col("weight")).alias("target"))


def thresholds(sized: DataFrame, budgets: DataFrame, levels: int = 3, bits: int = 12) -> DataFrame:
    """(source, threshold): rows with ``hash < threshold`` sum to within half the boundary bucket of the budget.

    ``sized``: (source, size, hash); ``budgets``: (source, budget). After ``levels`` refinements the boundary bucket is
    2**-(levels*bits) of the source, about one row; it is taken if that comes nearer to the budget.
    """
    found = budgets.select(F.col("source").alias("s"), "budget", F.lit(0).cast("long").alias("low"), F.lit(0).cast("long").alias("below"))
    found = checkpointed(found)
    for level in range(1, levels + 1):
        width = HASH_BITS - bits * level
        inside = sized.join(beside(found), sized["source"].eqNullSafe(found["s"]))
        if level > 1:
            inside = inside.where((F.col("hash") >= F.col("low")) & (F.col("hash") < F.col("low") + F.lit(2 ** (width + bits))))
        hist = inside.groupBy("s", "budget", "below", F.shiftright("hash", width).alias("bucket")).agg(F.sum("size").alias("here"))
        run = Window.partitionBy("s").orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        summed = hist.withColumn("upto", F.col("below") + F.sum("here").over(run))
        boundary = summed.where("upto > budget").groupBy("s", "budget").agg(F.min_by(F.struct("bucket", "here", "upto"), "bucket").alias("b"))
        found = boundary.select("s", "budget", F.shiftleft("b.bucket", width).alias("low"), (F.col("b.upto") - F.col("b.here")).alias("below"), F.col("b.upto").alias("upto"))
        found = checkpointed(found)
    width = HASH_BITS - bits * levels
    nearer = F.col("upto") - F.col("budget") < F.col("budget") - F.col("below")
    return found.select(F.col("s").alias("source"), F.when(nearer, F.col("low") + F.lit(2**width)).otherwise(F.col("low")).alias("threshold"))


def measured(docs: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """(doc_id, source, size, hash), written once: what the plan and its use need of the documents."""
    size = F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")
    return checkpointed(docs.select(F.col(id_col).alias("doc_id"), F.col(source).alias("source"), size.alias("size"), keyed_hash(F.col(id_col)).alias("hash")))


def mix_plan(sized: DataFrame, weights: Sequence[int] = (1, 2, 3), share: float = 1.0, most: int = 3) -> DataFrame:
    """(s, source_size, target, full, threshold): one row per source."""
    per = checkpointed(targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most))
    full = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    plan = per.withColumn("full", full).withColumn("budget", F.col("target") - F.col("full") * F.col("source_size"))
    cut = thresholds(sized, plan.where("budget > 0"))
    both = plan.alias("p").join(cut.alias("c"), F.col("p.source").eqNullSafe(F.col("c.source")), "left")
    return checkpointed(both.select(F.col("p.source").alias("s"), "source_size", "target", "full", F.coalesce("threshold", F.lit(0)).alias("threshold")))


def copies(hash_: Column) -> Column:
    """How often the mix takes a row that stands beside its source's plan."""
    return F.col("full") + F.when(hash_ < F.col("threshold"), 1).otherwise(0)


def mix(docs: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source", weights: Sequence[int] = (1, 2, 3), share: float = 1.0, most: int = 3) -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies) for every row; ``taken`` counts words, repeats included."""
    sized = measured(docs, id_col, text, source)
    plan = mix_plan(sized, weights, share, most)
    joined = sized.join(beside(plan), sized["source"].eqNullSafe(plan["s"]))
    return joined.select("doc_id", "size", "source_size", "target", (F.col("size") * copies(F.col("hash"))).alias("taken"), copies(F.col("hash")).alias("copies"))


def take_mix(docs: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source", weights: Sequence[int] = (1, 2, 3), share: float = 1.0, most: int = 3) -> DataFrame:
    """The documents of the mix with all their columns: a row for each time that a document is taken.

    The plan has a row per source and is joined by :func:`beside`, so texts are not shuffled while sources are few.
    """
    plan = mix_plan(measured(docs, id_col, text, source), weights, share, most)
    mine = plan.select(*[F.col(c).alias(f"__mix_{c}") for c in ("s", "full", "threshold")])
    times = F.col("__mix_full") + F.when(keyed_hash(F.col(id_col)) < F.col("__mix_threshold"), 1).otherwise(0)
    joined = docs.join(beside(mine), docs[source].eqNullSafe(mine["__mix_s"]))
    repeated = joined.withColumn("__mix_n", F.explode(F.when(times > 0, F.sequence(F.lit(1).cast("long"), times))))
    return repeated.select(*[F.col(f"`{c}`") for c in docs.columns])
