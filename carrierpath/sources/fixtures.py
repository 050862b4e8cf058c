"""The given tables seen as incidences, variant catalogues and paths."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.session import cut
from .tables import table


@dataclass
class Incidence:
    """Pairs (allele_id, hap_id, class) as they occur, repeats and all, and the cohort size."""

    pairs: DataFrame
    h: int


def _count(spark, d, name) -> int:
    return table(spark, d, name).count()


def _phase():
    return (F.col("l_linestatus") == "O").cast("long")


def supplier(spark: SparkSession, d: str) -> Incidence:
    parts = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.when(F.col("p_size") >= 49, "SV").otherwise("SNV").alias("class"))
    calls = table(spark, d, "lineitem").select("l_partkey", (2 * F.col("l_suppkey") + _phase()).alias("hap_id"))
    return Incidence(calls.join(parts, "l_partkey").select(F.col("l_partkey").alias("allele_id"), "hap_id", "class"), 2 * _count(spark, d, "supplier"))


def customer_unphased(spark: SparkSession, d: str) -> Incidence:
    lines = table(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("allele_id"))
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("hap_id"))
    return Incidence(lines.join(orders, "l_orderkey").select("allele_id", "hap_id", F.lit("SNV").alias("class")), _count(spark, d, "customer"))


def customer(spark: SparkSession, d: str, kind: str | None = None) -> Incidence:
    """All classes, or the alleles of class ``kind`` only: then lines of other parts do not meet the orders."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", _phase().alias("phase"))
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    names = F.array(
        F.struct(F.concat(F.lit("bt:"), "p_brand", F.lit("/"), "p_type").alias("allele_id"), F.lit("SNV").alias("class")),
        F.struct(F.concat(F.lit("bs:"), "p_brand", F.lit("/"), F.col("p_size").cast("string")).alias("allele_id"), F.lit("SNV").alias("class")),
        F.struct(F.concat(F.lit("n:"), "p_name").alias("allele_id"), F.lit("SNV").alias("class")),
        F.struct(F.when(F.col("p_size") >= 49, F.concat(F.lit("p:"), F.col("p_partkey").cast("string"))).alias("allele_id"), F.lit("SV").alias("class")),
    )
    parts = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.explode(names).alias("a")).where("a.allele_id is not null")
    if kind is not None:
        parts = parts.where(F.col("a.class") == kind)
        lines = lines.join(parts.select("l_partkey"), "l_partkey", "left_semi")
    pairs = lines.join(orders, "l_orderkey").join(parts, "l_partkey").select("a.allele_id", (2 * F.col("o_custkey") + F.col("phase")).alias("hap_id"), "a.class")
    return Incidence(pairs, 2 * _count(spark, d, "customer"))


def multiallelic(spark: SparkSession, d: str) -> DataFrame:
    """Calls (site_id, alt_no, hap_id): one alternative for each return flag, the smallest flag of a pair kept."""
    alt = F.when(F.col("l_returnflag") == "A", 1).when(F.col("l_returnflag") == "N", 2).otherwise(3)
    calls = table(spark, d, "lineitem").select(F.col("l_partkey").alias("site_id"), alt.alias("alt_no"), (2 * F.col("l_suppkey") + _phase()).alias("hap_id"))
    return calls.groupBy("site_id", "hap_id").agg(F.min("alt_no").alias("alt_no")).select("site_id", "alt_no", "hap_id")


def tokens(spark: SparkSession, d: str) -> Incidence:
    size = F.length("allele_id")
    words = table(spark, d, "documents").select(F.explode(F.split("text", " ")).alias("allele_id"), F.col("doc_id").alias("hap_id")).where("allele_id <> ''")
    return Incidence(words.withColumn("class", F.when(size <= 4, "short").when(size <= 11, "mid").otherwise("long")), _count(spark, d, "documents"))


def events(spark: SparkSession, d: str) -> Incidence:
    seen = table(spark, d, "events")
    h = seen.agg(F.max("user_id")).first()[0] + 1
    return Incidence(seen.select(F.concat("event_type", F.lit(":"), F.get_json_object("props", "$.k")).alias("allele_id"), F.col("user_id").alias("hap_id"), F.lit("SNV").alias("class")), h)


def embeddings(spark: SparkSession, d: str, above: float = 0.0) -> Incidence:
    each = table(spark, d, "embeddings").select(F.col("vec_id").alias("hap_id"), F.posexplode("embedding").alias("at", "value")).where(F.col("value") > above)
    return Incidence(each.select((F.col("at") + 1).cast("long").alias("allele_id"), "hap_id", F.lit("SNV").alias("class")), _count(spark, d, "embeddings"))


def benchmark(spark: SparkSession, d: str) -> Incidence:
    shared = table(spark, d, "benchmark").select(F.explode(F.split("text", " ")).alias("allele_id")).where("allele_id <> ''").distinct()
    own = tokens(spark, d)
    return Incidence(own.pairs.join(shared, "allele_id", "left_semi"), own.h)


INCIDENCES = {"supplier": supplier, "customer": customer, "customer_unphased": customer_unphased, "tokens": tokens, "events": events, "embeddings": embeddings, "benchmark": benchmark}


def catalogue(spark: SparkSession, d: str, kind: str = "plain") -> DataFrame:
    """(contig, allele_id, pos, ref_len, class) of the variants on one contig; 'insertions' and 'overlapping' are variants of it."""
    size = F.col("p_size")
    sv = size >= (40 if kind == "overlapping" else 49)
    length = (100 if kind == "overlapping" else 10) * size
    if kind == "insertions":
        length = F.when(size == 49, 0).otherwise(length)
    return table(spark, d, "part").select(
        F.lit("c1").alias("contig"), F.col("p_partkey").alias("allele_id"), (1000 * F.col("p_partkey") + 250).alias("pos"),
        F.when(sv, length).otherwise(1).cast("long").alias("ref_len"), F.when(sv, "SV").otherwise("SNV").alias("class"),
    )


def region(spark: SparkSession, d: str) -> tuple[int, int]:
    return 0, 1000 * _count(spark, d, "part")


# Paths (path_id, seq, label), in order within a path; seq need not be dense ---------------


def event_paths(spark, d):
    return table(spark, d, "events").select(F.col("user_id").alias("path_id"), F.struct("ts").alias("at"), F.col("event_type").alias("label"))


def role_paths(spark, d):
    return table(spark, d, "conversations").select(F.col("conv_id").alias("path_id"), F.struct("turn").alias("at"), F.col("role").alias("label"))


def brand_paths(spark, d):
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    parts = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("label"))
    return lines.join(parts, "l_partkey").select(F.col("l_orderkey").alias("path_id"), F.struct("l_linenumber", "l_partkey").alias("at"), "label")


def word_texts(spark, d):
    """(path_id, text) of documents, with blanks between labels."""
    return table(spark, d, "documents").select(F.col("doc_id").alias("path_id"), "text")


def word_arrays(spark, d, longest: int | None = None):
    """(path_id, labels) of documents: a path stays in its row."""
    docs = table(spark, d, "documents")
    if longest is not None:
        docs = docs.where(F.col("n_chars") <= longest)
    return docs.select(F.col("doc_id").alias("path_id"), F.filter(F.split("text", " "), lambda x: x != "").alias("labels"))


def tag_arrays(spark, d):
    return table(spark, d, "pages").select(F.col("page_id").alias("path_id"), F.regexp_extract_all("html", F.lit("<[a-z][a-z0-9]*"), 0).alias("labels"))


def _steps(walks: DataFrame) -> DataFrame:
    return walks.select("path_id", F.posexplode("labels").alias("at", "label")).select("path_id", F.struct("at").alias("at"), "label")


def word_paths(spark, d, longest: int | None = None):
    own = word_arrays(spark, d, longest)
    return _steps(own if longest is None else cut(own))  # short documents are a small part of a table that is read once for them


def tag_paths(spark, d):
    return _steps(tag_arrays(spark, d))


def arrays(steps: DataFrame) -> DataFrame:
    """(path_id, labels) from (path_id, at, label)."""
    return steps.groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("at", "label"))).alias("s")).select("path_id", F.col("s.label").alias("labels"))
