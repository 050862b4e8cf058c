"""Carrier rows: one row per allele, each as a bitmap or an id list, whichever costs less.

Pairs are combined to words of 64 bits by ``bit_or`` before they are shuffled; the count of a row's bits
then tells its form, and only that form is built, so no list exceeds the crossover.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import bitops as B
from . import cost


def long_words(inc: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """(allele_id, word_no, word) of the non-empty words."""
    return inc.groupBy("allele_id", *keep, F.floor(F.col("hap_id") / B.WORD).cast("long").alias("word_no")).agg(F.bit_or(B.bit_of(F.col("hap_id"))).alias("word"))


def to_words(inc: DataFrame, h: int) -> DataFrame:
    """(allele_id, words) with all ceil(h / 64) words."""
    n = -(-h // B.WORD)
    got = long_words(inc).groupBy("allele_id").agg(F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("_held"))
    return got.select("allele_id", B.words_of_held(F.col("_held"), n).alias("words"))


def to_chunks(inc: DataFrame) -> DataFrame:
    """(allele_id, chunk, bitmap): chunks of 32,768 bits for large cohorts; empty chunks are not stored."""
    one = F.col("hap_id") + 1  # bucket numbers count from 1
    return inc.select("allele_id", F.bitmap_bucket_number(one).alias("chunk"), F.bitmap_bit_position(one).alias("place")).groupBy("allele_id", "chunk").agg(F.bitmap_construct_agg("place").alias("bitmap"))


def to_lists(inc: DataFrame) -> DataFrame:
    return inc.groupBy("allele_id").agg(F.sort_array(F.collect_set("hap_id")).alias("carriers"))


def encode(inc: DataFrame, h: int, policy: str = "min_cost", overhead_bits: int = 0) -> DataFrame:
    """(allele_id, class, k, enc, carriers, words, bits) of pairs (allele_id, hap_id, class); the unused branch is null.

    Pairs become words of 64 bits before the first shuffle, which also takes repeated pairs together; the second one brings
    a row's words together, at most h / 64 of them. Counts, lists and bitmaps all come from these, so pairs are read once.
    """
    held = inc.groupBy("allele_id", F.floor(F.col("hap_id") / B.WORD).cast("long").alias("word_no"))
    held = held.agg(F.bit_or(B.bit_of(F.col("hap_id"))).alias("word"), F.min("class").alias("class"))
    own = held.groupBy("allele_id").agg(
        F.min("class").alias("class"), F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).cast("long").alias("k"), F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("_held")
    )
    priced = cost.per_row(own, h, policy, overhead_bits)
    return priced.select(
        "allele_id", "class", "k", "enc", F.when(F.col("enc") == "list", B.carriers_of_held(F.col("_held"))).alias("carriers"),
        F.when(F.col("enc") == "bitmap", B.words_of_held(F.col("_held"), -(-h // B.WORD))).alias("words"), F.col("bits_hybrid").alias("bits"),
    )


def encode_complement(absent: DataFrame, links: DataFrame, h: int, policy: str = "min_cost") -> DataFrame:
    """(link, k, enc, carriers, words, bits) of each of ``links``, carried by all of h haplotypes but those of ``absent`` (link, hap_id), which may repeat.

    The shuffles are those of :func:`encode` on the absent pairs; a row turns round where it is made.
    """
    held = absent.groupBy("link", F.floor(F.col("hap_id") / B.WORD).cast("long").alias("word_no")).agg(F.bit_or(B.bit_of(F.col("hap_id"))).alias("word"))
    gone = held.groupBy("link").agg(F.sum(F.bit_count("word")).cast("long").alias("_gone"), F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("_held"))
    own = links.select("link").join(gone, "link", "left").withColumn("k", F.lit(h).cast("long") - F.coalesce("_gone", F.lit(0))).where("k > 0")
    words = B.words_of_rest(F.coalesce("_held", F.array().cast("array<struct<word_no:bigint,word:bigint>>")), h)
    return cost.per_row(own, h, policy).select(
        "link", "k", "enc", F.when(F.col("enc") == "list", B.carriers_of_words(words)).alias("carriers"), F.when(F.col("enc") == "bitmap", words).alias("words"), F.col("bits_hybrid").alias("bits"),
    )


def encode_varint(inc: DataFrame, h: int) -> DataFrame:
    """(allele_id, class, k, enc, packed, words, bits): like :func:`encode`, with lists stored as bytes of their steps.

    A list takes a byte for each id at least, so none has more than h / 8 ids.
    """
    held = inc.groupBy("allele_id", F.floor(F.col("hap_id") / B.WORD).cast("long").alias("word_no")).agg(F.bit_or(B.bit_of(F.col("hap_id"))).alias("word"), F.min("class").alias("class"))
    own = held.groupBy("allele_id").agg(F.min("class").alias("class"), F.sum(F.bit_count("word")).cast("long").alias("k"), F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("_held"))
    own = own.withColumn("_ids", F.when(8 * F.col("k") <= h, B.carriers_of_held(F.col("_held"))))
    own = own.withColumn("_bits", F.when(F.col("_ids").isNotNull(), 8 * B.varint_length(F.col("_ids")))).withColumn("enc", F.when(F.col("_bits") <= h, "list").otherwise("bitmap"))
    return own.select(
        "allele_id", "class", "k", "enc", F.when(F.col("enc") == "list", B.varint_bytes(F.col("_ids"))).alias("packed"),
        F.when(F.col("enc") == "bitmap", B.words_of_held(F.col("_held"), -(-h // B.WORD))).alias("words"), F.when(F.col("enc") == "list", F.col("_bits")).otherwise(F.lit(h)).cast("long").alias("bits"),
    )


def decode_varint(rows: DataFrame) -> DataFrame:
    """(allele_id, hap_id): the exact inverse of :func:`encode_varint`; rows are read once."""
    listed = F.col("enc") == "list"
    each = rows.select("allele_id", "enc", F.posexplode(F.when(listed, B.varint_steps(F.col("packed"))).otherwise(B.carriers_of_words(F.col("words")))).alias("at", "x"))
    so_far = Window.partitionBy("allele_id").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    return each.select("allele_id", F.when(listed, F.sum("x").over(so_far)).otherwise(F.col("x")).alias("hap_id"))


def decode(rows: DataFrame) -> DataFrame:
    """(allele_id, hap_id): the exact inverse of :func:`encode`."""
    ids = F.when(F.col("enc") == "list", F.col("carriers")).otherwise(B.carriers_of_words(F.col("words")))
    return rows.select("allele_id", F.explode(ids).alias("hap_id"))


def merge(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of two sets over one cohort. An allele in both is an error that the result raises when it is read."""
    both = a.withColumn("_side", F.lit(1)).unionByName(b.withColumn("_side", F.lit(2)))
    twice = both.groupBy("allele_id").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select("allele_id", "_n")
    checked = both.join(twice, "allele_id", "left")
    ok = F.when(F.col("_n").isNotNull(), F.raise_error(F.concat(F.lit("allele in both sets: "), F.col("allele_id").cast("string")))).otherwise(F.col("allele_id"))
    return checked.withColumn("allele_id", ok.cast(a.schema["allele_id"].dataType)).drop("_side", "_n")


def export_relation(rows: DataFrame, drop: tuple[str, ...] = ("ann",), salt: str | None = None) -> DataFrame:
    """Incidence without annotations; with a salt, allele ids become salted digests."""
    out = rows.drop(*drop)
    return out if salt is None else out.withColumn("allele_id", F.sha2(F.concat(F.col("allele_id").cast("string"), F.lit(salt)).cast("binary"), 256))
