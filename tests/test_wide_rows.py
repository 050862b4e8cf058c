"""Rows of wide cohorts: bytes of lists, words from few ids, and how many rows move."""

import random
import time

from pyspark.sql import functions as F

from carrierpath.functions import bitops as B
from carrierpath.operators import rows

from .test_runs import moved


def packed(ids):
    out, last = b"", 0
    for x in ids:
        step, last = x - last, x
        while step > 127:
            out, step = out + bytes([step & 127 | 128]), step >> 7
        out += bytes([step])
    return out


def test_bytes_of_lists_and_their_length(spark):
    r = random.Random(1)
    lists = [(i, sorted({r.randrange(1 << r.randrange(1, 45)) for _ in range(r.randrange(1, 30))} | {63, 127})) for i in range(200)]
    df = spark.createDataFrame(lists, "i long, ids array<long>")
    for x in df.select("ids", B.varint_bytes(F.col("ids")).alias("b"), B.varint_length(F.col("ids")).alias("n"), B.varint_steps(B.varint_bytes(F.col("ids"))).alias("s")).collect():
        assert bytes(x["b"]) == packed(x["ids"]) and x["n"] == len(x["b"]) and x["s"] == [b - a for a, b in zip([0, *x["ids"]], x["ids"], strict=False)]


def test_varint_rows_move_pairs_twice_at_most(spark):
    r = random.Random(2)
    pairs = sorted({(f"a{r.randrange(20)}", r.randrange(3000)) for _ in range(6000)} | {("full", i) for i in range(3000)})
    inc = spark.createDataFrame([(a, h, "SNV") for a, h in pairs], "allele_id string, hap_id long, class string")
    enc = rows.encode_varint(inc, 3000)
    assert {x["enc"] for x in enc.select("enc").collect()} == {"list", "bitmap"}
    got, n = moved(spark, lambda: rows.decode_varint(enc).collect())
    assert sorted(map(tuple, got)) == pairs and n <= 2 * len(pairs)


def test_words_of_a_wide_cohort_take_time_by_their_number(spark):
    """Each word was searched in all held ones before: 2 * 10^10 steps here."""
    held = spark.range(20_000).select(F.struct((F.col("id") * 100 + 7).alias("word_no"), F.lit(5).cast("long").alias("word")).alias("x")).agg(F.array_sort(F.collect_list("x")).alias("h"))
    began = time.time()
    words = B.words_of_held(F.col("h"), 2_000_000)
    got = held.select(F.size(words).alias("n"), B.popcount_words(words).alias("k")).first()
    assert tuple(got) == (2_000_000, 40_000) and time.time() - began < 15
