"""Range and as-of joins without nested loops."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def covering(points: DataFrame, spans: DataFrame, width: int, point: str = "pos", lo: str = "start", hi: str = "end", by: str = "contig") -> DataFrame:
    """Each point with the spans lo <= point < hi: an equi-join on bins of ``width``, then the predicate.

    A span stands in each bin that it touches, so choose the width near the usual length of a span.
    """
    binned = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.greatest(F.col(hi), F.col(lo) + 1) - 1) / width))))
    return points.withColumn("_bin", F.floor(F.col(point) / width)).join(binned, [by, "_bin"]).where((F.col(lo) <= F.col(point)) & (F.col(point) < F.col(hi))).drop("_bin")


def latest_at(points: DataFrame, marks: DataFrame, point: str, mark: str, value: str, by: str = "contig") -> DataFrame:
    """(points, ``value`` of the last mark at or before each point): a union and one ordered window by contig."""
    m = marks.select(F.col(by), F.col(mark).alias("_at"), F.col(value).alias("_v"), F.lit(0).alias("_k"))
    p = points.withColumn("_row", F.struct(*points.columns)).select(F.col(by), F.col(point).alias("_at"), F.lit(1).alias("_k"), "_row")
    both = m.unionByName(p, allowMissingColumns=True)
    last = F.last("_v", ignorenulls=True).over(Window.partitionBy(by).orderBy("_at", "_k").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn(f"last_{value}", last).where("_k = 1").select("_row.*", f"last_{value}")
