"""First-order transition model of walks, smoothed on the observed support."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Reserved codes of the start context, the end symbol and the escape symbol.
START, STOP, ESC = -1, -2, -3


def transitions(paths: DataFrame) -> DataFrame:
    """(path_id, seq, ctx, sym) of (path_id, nodes): a zip inside each row, so no shuffle and no window."""
    lit = lambda x: F.array(F.lit(x).cast("long"))
    steps = F.arrays_zip(F.concat(lit(START), "nodes").alias("ctx"), F.concat("nodes", lit(STOP)).alias("sym"))
    return paths.select("path_id", F.posexplode(steps).alias("seq", "t")).select("path_id", "seq", F.col("t").getField("ctx").alias("ctx"), F.col("t").getField("sym").alias("sym"))


def count(paths: DataFrame) -> DataFrame:
    """(ctx, sym, n), summed partly before the one shuffle."""
    return transitions(paths).groupBy("ctx", "sym").agg(F.count(F.lit(1)).alias("n"))


def count_labels(walks: DataFrame) -> DataFrame:
    """(src, dst, n) of (path_id, labels): transitions counted before their labels have numbers; src is null at the start, dst at the end.

    Paths without a label have no transitions.
    """
    end = F.array(F.lit(None).cast("string"))
    steps = F.arrays_zip(F.concat(end, "labels").alias("src"), F.concat("labels", end).alias("dst"))
    each = walks.where(F.size("labels") > 0).select(F.explode(steps).alias("t"))
    return each.select(F.col("t").getField("src").alias("src"), F.col("t").getField("dst").alias("dst")).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def number(counted: DataFrame, index: DataFrame) -> DataFrame:
    """(ctx, sym, n) of counted labels (src, dst, n) and their index (label, idx).

    A row of each distinct transition is joined, not one of each step; ends have fixed numbers and are not joined, as no other row is as frequent.
    """
    src, dst = (index.select(F.col("label").alias(x), F.col("idx").alias(y)) for x, y in (("src", "ctx"), ("dst", "sym")))
    begun = counted.where("src is null").withColumn("ctx", F.lit(START).cast("long")).drop("src")
    by_ctx = begun.unionByName(counted.where("src is not null").join(src, "src").drop("src"))
    ended = by_ctx.where("dst is null").withColumn("sym", F.lit(STOP).cast("long")).drop("dst")
    return ended.unionByName(by_ctx.where("dst is not null").join(dst, "dst").drop("dst")).select("ctx", "sym", "n")


def update(counts: DataFrame, delta: DataFrame) -> DataFrame:
    return counts.select("ctx", "sym", "n").unionByName(delta.select("ctx", "sym", "n")).groupBy("ctx", "sym").agg(F.sum("n").cast("long").alias("n"))


def touched(delta: DataFrame) -> DataFrame:
    """Contexts whose codes an update changes."""
    return delta.select("ctx").distinct()


def weights(counts: DataFrame, alpha: float = 1.0, force_stop: bool = True, escape: str = "off", stop_smoothing: str = "single") -> DataFrame:
    """(ctx, sym, n, w): w = n + alpha on symbols seen after the context, and on the end symbol if forced, and on the escape symbol unless 'off'.

    ``stop_smoothing='double'`` adds alpha to a seen end symbol twice.
    """
    own = counts.select("ctx", "sym", "n")
    if force_stop or escape != "off":
        more = ([STOP] if force_stop else []) + ([ESC] if escape != "off" else [])
        forced = own.select("ctx").distinct().select("ctx", F.explode(F.array(*[F.lit(x).cast("long") for x in more])).alias("sym"), F.lit(0).cast("long").alias("n"))
        own = own.unionByName(forced).groupBy("ctx", "sym").agg(F.sum("n").cast("long").alias("n"))
    w = F.col("n") + F.lit(float(alpha))
    if stop_smoothing == "double":
        w = w + F.when((F.col("sym") == STOP) & (F.col("n") > 0), F.lit(float(alpha))).otherwise(0.0)
    return own.withColumn("w", w)
