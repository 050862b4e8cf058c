"""Readers of tables and of phased genotype text, and writers of what the engine makes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_genotypes(spark: SparkSession, path: str, missing: str = "absent", unphased: str = "error") -> DataFrame:
    """Phased genotype text -> calls (contig, pos, site_id, ref, alt, sv_type, sample_no, phase, allele).

    Lines are tab-separated: contig, position, id, reference, alternatives, quality, filter, info, format, then
    a call for each sample. ``missing`` is 'absent' or 'error', ``unphased`` 'as_is' or 'error'.
    """
    lines = spark.read.text(path).where(~F.col("value").startswith("#") & (F.col("value") != ""))
    f = F.split("value", "\t")
    sites = lines.select(
        f[0].alias("contig"), f[1].cast("long").alias("pos"), f[2].alias("site_id"), f[3].alias("ref"), f[4].alias("alt"),
        F.nullif(F.regexp_extract(f[7], r"(?:^|;)SVTYPE=([^;]+)", 1), F.lit("")).alias("sv_type"),
        F.posexplode(F.slice(f, 10, F.size(f))).alias("sample_no", "call"),
    )
    gt = F.split("call", ":")[0]
    calls = sites.withColumn("gt", gt)
    if unphased == "error":
        calls = calls.withColumn("gt", F.when(F.col("gt").contains("/"), F.raise_error(F.concat(F.lit("unphased call at "), "site_id"))).otherwise(F.col("gt")))
    each = calls.select("contig", "pos", "site_id", "ref", "alt", "sv_type", "sample_no", F.posexplode(F.split("gt", r"[|/]")).alias("phase", "allele"))
    if missing == "error":
        each = each.withColumn("allele", F.when(F.col("allele") == ".", F.raise_error(F.concat(F.lit("missing call at "), "site_id"))).otherwise(F.col("allele")))
    return each.where("allele <> '.'").withColumn("allele", F.col("allele").cast("int"))


def read_edges(spark: SparkSession, path: str) -> DataFrame:
    """Edge map lines 'edge_id<TAB>src<TAB>dst'."""
    f = F.split("value", "\t")
    return spark.read.text(path).where("value <> ''").select(f[0].cast("long").alias("edge_id"), f[1].alias("src"), f[2].alias("dst"))


def read_paths(spark: SparkSession, path: str) -> DataFrame:
    """Walk lines 'path_id<TAB>node,node,...' -> (path_id, nodes)."""
    f = F.split("value", "\t")
    nodes = F.when(f[1] == "", F.array().cast("array<string>")).otherwise(F.split(f[1], ","))
    return spark.read.text(path).where("value <> ''").select(f[0].cast("long").alias("path_id"), nodes.alias("nodes"))


def write_clustered(df: DataFrame, path: str, key: str, files: int | None = None, partition_by: tuple[str, ...] = ()) -> None:
    """Parquet clustered by ``key``, so that row-group statistics prune reads of single keys."""
    spread = df.repartitionByRange(files, key) if files else df.repartitionByRange(key)
    out = spread.sortWithinPartitions(key).write.mode("overwrite")
    (out.partitionBy(*partition_by) if partition_by else out).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by ``key``: joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def write_text(lines: DataFrame, path: str) -> None:
    lines.write.mode("overwrite").text(path)
