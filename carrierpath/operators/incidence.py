"""The allele by haplotype relation: construction, classes, windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def from_calls(calls: DataFrame, multiallelic: str = "split", alleles: str = "allele_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """Distinct pairs (allele_id, hap_id) of calls; the reference allele (0) has no row.

    Calls are (allele_id, hap_id), or (site_id, alt_no, hap_id): then 'split' makes a row for each
    alternative and 'collapse' one for each site. The shuffle is by allele and haplotype with partial aggregation.
    """
    if "alt_no" in calls.columns:
        calls = calls.where("alt_no > 0")
        name = F.col("site_id") if multiallelic == "collapse" else F.concat_ws(":", "site_id", "alt_no")
        calls = calls.withColumn(alleles, name)
    return calls.select(F.col(alleles).alias("allele_id"), "hap_id", *keep).dropDuplicates(["allele_id", "hap_id"])


def classify(df: DataFrame, rule: Column, yes: str = "SV", no: str = "SNV") -> DataFrame:
    return df.withColumn("class", F.when(rule, yes).otherwise(no))


def window(df: DataFrame, lo: int, hi: int, samples: DataFrame | None = None) -> DataFrame:
    """Rows with lo <= pos < hi, of the given samples (sample_id) only."""
    out = df.where((F.col("pos") >= lo) & (F.col("pos") < hi))
    return out if samples is None else out.join(samples.select("sample_id"), "sample_id", "left_semi")


def counts(inc: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(allele_id, *by, k) of pairs that may repeat."""
    pairs = inc.select("allele_id", "hap_id", *by).distinct()
    return pairs.groupBy("allele_id", *by).agg(F.count(F.lit(1)).alias("k"))
