"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Every row gets an exponential key, scaled by its quality weight: ``-ln(u) / weight``
with ``u`` a hash of its id and size, so that reruns agree. A source whose target is r times its
size gives floor(r) complete epochs; the remaining budget goes to the rows with the
smallest keys, by a prefix sum in key order.

No source is ever sorted in one task. The keys are cut into ``BUCKETS`` ranges; sums
of each (source, range) show the one range in which the budget ends, all ranges
before it are taken whole, and only the rows of that range are sorted.

Null texts have size 0, null sources are a source of their own and come last, rows
with equal keys are ordered by id and size, repeated rows count each for themselves,
a missing or non-positive weight counts as the least one, and an empty table gives
an empty mix.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, one_of_each_key, text_of, uniform, word_count

#: Weights of the sources in code point order, repeating.
SOURCE_WEIGHTS = (1.0, 2.0, 3.0)
#: A source gives at most so many times its size.
MAX_REPEATS = 3
#: Sampling weights by the label of quality: good, poor, none.
QUALITY_WEIGHTS = (1.0, 0.5, 0.75)
BUCKETS = 2048
#: A table of sources up to this many rows (under 100 bytes each) is broadcast.
BROADCAST_ROWS = 50_000


def fill_targets(sources: DataFrame, total: Column, cap: int) -> DataFrame:
    """Targets of ``sources`` (source, source_size, weight): shares of ``total`` by weight, none above cap * size.

    Resharing the excess until none is above ends where all capped sources have a
    smaller cap per weight than the level of the others, so one pass in the order of
    that ratio finds the level. One row for each source goes through one task.
    """
    order = Window.orderBy(F.col("ratio"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    walk = (
        sources.withColumn("most", F.lit(float(cap)) * F.col("source_size"))
        .withColumn("ratio", F.col("most") / F.col("weight"))
        .withColumn("spent", F.coalesce(F.sum("most").over(before), F.lit(0.0)))
        .withColumn("left_weight", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", (total - F.col("spent")) / F.col("left_weight"))
    )
    # The level at the first source that stays below its cap holds for all after it.
    first = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", (-F.col("level")).alias("minus")))).over(Window.partitionBy())
    capped = first.isNull() | (F.col("ratio") < first["ratio"])
    return walk.select(
        "source", "source_size", F.when(capped, F.col("most")).otherwise(-F.col("weight") * first["minus"]).alias("target")
    )


def source_targets(sized: DataFrame, weights=SOURCE_WEIGHTS, cap: int = MAX_REPEATS) -> DataFrame:
    """(source, source_size, target) of rows (source, size)."""
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (place % len(weights) + 1).cast("int"))
    weighted = sums.withColumn("weight", weight)
    total = F.sum("source_size").over(Window.partitionBy()).cast("double")
    return fill_targets(weighted.withColumn("total", total), F.col("total"), cap)


def mix(
    docs: DataFrame,
    quality: Column | None = None,
    labels: DataFrame | None = None,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights=SOURCE_WEIGHTS,
    cap: int = MAX_REPEATS,
    buckets: int = BUCKETS,
    row_col: str | None = None,
) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken), one row per row of ``docs``; and its column ``row_col``.

    ``quality`` is the sampling weight of a row; without it the weight comes from
    ``labels`` (doc_id, quality), and without either it is 1. A row is chosen for the
    last, partial epoch while the larger part of it fits into the budget.
    """
    size = word_count(text_of(text_col))
    key = (row_col,) if row_col else ()
    sized = docs.select(
        F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"),
        (quality if quality is not None else F.lit(1.0)).alias("weight"), *key,
    )
    if quality is None and labels is not None:  # joined to sizes, so that no text is shuffled
        sized = with_quality(sized.drop("weight"), labels).withColumnRenamed("quality_weight", "weight")
    sized = sized.withColumn("weight", F.greatest(F.coalesce("weight", F.lit(1e-6)), F.lit(1e-6)))
    sized = sized.withColumn("key", -F.log(uniform(F.col("doc_id"), F.col("size"))) / F.col("weight"))
    # 1 - exp(-key) grows with the key and spreads keys of weight 1 evenly.
    sized = cut(
        sized.select(
            "doc_id", "source", "size", "key", *key,
            F.least(F.floor((1 - F.exp(-F.col("key"))) * buckets), F.lit(buckets - 1)).cast("int").alias("bucket"),
        )
    )
    targets = source_targets(sized, weights, cap)
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    plan = targets.withColumn("epochs", F.least(epochs, F.lit(cap))).withColumn(
        "budget", F.col("target") - F.col("epochs") * F.col("source_size")
    )
    sums = sized.groupBy("source", "bucket").agg(F.sum("size").alias("words"))
    running = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    sums = sums.withColumn("up_to", F.sum("words").over(running))
    # Through the last range that still fits whole; the next one is the last that is looked at.
    ends = (
        sums.alias("b").join(plan.alias("p"), F.col("b.source").eqNullSafe(F.col("p.source")))
        .where(F.col("up_to") > F.col("budget"))
        .groupBy(F.col("p.source").alias("source"))
        .agg(F.min(F.struct("bucket", (F.col("up_to") - F.col("words")).alias("before"))).alias("end"))
    )
    plan = cut(
        plan.alias("p").join(ends.alias("e"), F.col("p.source").eqNullSafe(F.col("e.source")), "left").select(
            F.col("p.source").alias("of"), "source_size", "target", "epochs", "budget",
            F.coalesce(F.col("end.bucket"), F.lit(buckets)).alias("last_bucket"),
            F.coalesce(F.col("end.before"), F.lit(0)).alias("before"),
        )
    )
    if plan.count() <= BROADCAST_ROWS:
        plan = F.broadcast(plan)
    rows = sized.join(plan, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    whole = rows.where(F.col("bucket") != F.col("last_bucket")).withColumn(
        "chosen", F.col("bucket") < F.col("last_bucket")
    )
    in_order = Window.partitionBy("source").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    sofar = F.col("before") + F.coalesce(F.sum("size").over(in_order), F.lit(0))
    last = rows.where(F.col("bucket") == F.col("last_bucket")).withColumn(
        "chosen", sofar + F.col("size") / 2 <= F.col("budget")
    )
    copies = F.least(F.col("epochs") + F.col("chosen").cast("long"), F.lit(cap))
    return whole.unionByName(last).select(
        "doc_id", "source", "size", "source_size",
        F.round("target", 6).alias("target"), copies.alias("copies"), (copies * F.col("size")).alias("taken"), *key,
    )


def with_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", weights=QUALITY_WEIGHTS) -> DataFrame:
    """``docs`` with a column quality_weight from labels (doc_id, quality); several labels count as the best."""
    good, poor, none = weights
    best = labels.groupBy(F.col("doc_id").alias("_labelled")).agg(F.max("quality").alias("_quality"))
    value = F.when(F.col("_quality") == 1, good).when(F.col("_quality") == 0, poor).otherwise(none)
    return docs.join(best, F.col(id_col) == F.col("_labelled"), "left").withColumn("quality_weight", value).drop(
        "_labelled", "_quality"
    )


def mixed_rows(docs: DataFrame, mixed: DataFrame, row_col: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them.

    ``row_col``, given to :func:`mix` too, tells rows apart and must not be null; rows that share it are alike and give the sum of their copies.
    """
    times = mixed.groupBy(F.col(row_col).alias("_taken")).agg(F.sum("copies").cast("int").alias("_copies")).where("_copies > 0")
    return (
        one_of_each_key(docs, row_col).join(times, F.col(row_col) == F.col("_taken"))
        .withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
        .select(*docs.columns)
    )
