"""Costs of the encodings and where they break even."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bitops as B


def break_even(h: int) -> tuple[float, int]:
    """(real, integer): H / log2 H, and the largest carrier count whose list is no longer than the bitmap."""
    real = h / math.log2(h) if h > 1 else float(h)
    return real, h // B.id_width(h)


def per_row(counted: DataFrame, h: int, policy: str = "min_cost", overhead_bits: int = 0) -> DataFrame:
    """Costs beside each row (allele_id, k, ...)."""
    k = F.col("k")
    enc = B.row_encoding(k, h, policy)
    dense, listed = B.bits_dense(h) + overhead_bits, B.bits_list(k, h) + overhead_bits
    return counted.withColumns(
        {"bits_dense": dense, "bits_list": listed, "enc": enc, "bits_hybrid": F.when(enc == "list", listed).otherwise(dense)}
    )


def by_class(costs: DataFrame, by: str = "class") -> DataFrame:
    """Totals by class: rows, encodings, bits of each policy, ratio and reduction."""
    total = lambda c: F.sum(c).cast("long")
    out = costs.groupBy(by).agg(
        F.count(F.lit(1)).alias("n_rows"), total((F.col("enc") == "list").cast("long")).alias("n_list"), total((F.col("enc") == "bitmap").cast("long")).alias("n_bitmap"),
        total("bits_dense").alias("bits_bitmap"), total("bits_list").alias("bits_list"), total("bits_hybrid").alias("bits_hybrid"),
    )
    ratio = F.col("bits_hybrid") / F.col("bits_bitmap")
    return out.withColumn("ratio", F.round(ratio, 6)).withColumn("reduction", F.round(1 - ratio, 6))


def _varint_bytes(x):
    return F.greatest(F.lit(1), F.ceil(F.length(F.bin(x)) / 7)).cast("long")


def delta_varint(inc: DataFrame, h: int) -> DataFrame:
    """(allele_id, k, bits_varint): lists as bytes of seven bits of the differences of ascending ids (the first id itself).

    A lag within the allele, so no list is collected.
    """
    from pyspark.sql import Window

    step = F.col("hap_id") - F.coalesce(F.lag("hap_id").over(Window.partitionBy("allele_id").orderBy("hap_id")), F.lit(0))
    each = inc.select("allele_id", "hap_id").distinct().select("allele_id", (8 * _varint_bytes(step)).alias("bits"))
    return each.groupBy("allele_id").agg(F.count(F.lit(1)).alias("k"), F.sum("bits").cast("long").alias("bits_varint"))


def container_bitmap(inc: DataFrame, h: int, chunk: int = 1 << 16) -> DataFrame:
    """(allele_id, k, bits_container): each chunk of ids as the least of 16-bit ids, a bitmap and runs of 32 bits."""
    from pyspark.sql import Window

    pairs = inc.select("allele_id", "hap_id").distinct().withColumn("chunk", F.floor(F.col("hap_id") / chunk))
    last = F.lag("hap_id").over(Window.partitionBy("allele_id", "chunk").orderBy("hap_id"))
    starts = pairs.withColumn("starts", (last.isNull() | (F.col("hap_id") != last + 1)).cast("long"))
    per = starts.groupBy("allele_id", "chunk").agg(F.count(F.lit(1)).alias("k"), F.sum("starts").alias("runs"))
    room = F.least(F.lit(chunk), F.lit(h) - F.col("chunk") * chunk)
    per = per.withColumn("bits", F.least(16 * F.col("k"), room, 32 * F.col("runs")))
    return per.groupBy("allele_id").agg(F.sum("k").cast("long").alias("k"), F.sum("bits").cast("long").alias("bits_container"))
