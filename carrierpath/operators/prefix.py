"""One Huffman code per context, built once per distinct weight profile.

Symbols of a context are ranked by weight, then symbol; the profile is the array of ranked weights. Equal
profiles have equal code lengths whatever their symbols, so the kernel runs on distinct
profiles only. Among equal weights the subtree with the smallest rank is merged first, so lengths depend on the profile alone.
"""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def huffman(profile: list[float], single: str = "empty") -> list[int]:
    """Code lengths of weights in ascending order."""
    n = len(profile)
    if n == 1:
        return [0 if single == "empty" else 1]
    heap = [(w, r, r) for r, w in enumerate(profile)]  # ascending, so already a heap
    above = [0] * (2 * n - 1)
    for node in range(n, 2 * n - 1):
        w1, r1, a = heapq.heappop(heap)
        w2, r2, b = heapq.heappop(heap)
        above[a] = above[b] = node
        heapq.heappush(heap, (w1 + w2, min(r1, r2), node))
    depth = [0] * (2 * n - 1)
    for node in range(2 * n - 3, -1, -1):
        depth[node] = depth[above[node]] + 1
    return depth[:n]


def lengths_of(single: str = "empty"):
    @F.pandas_udf(T.ArrayType(T.IntegerType()))
    def huffman_lengths(profiles: pd.Series) -> pd.Series:
        return profiles.map(lambda p: huffman(list(p), single))

    return huffman_lengths


def lengths(weighted: DataFrame, cache: str = "profile", single_symbol: str = "empty") -> DataFrame:
    """(ctx, sym, n, w, rank, len, sig); ``cache`` tells which contexts share a code.

    'profile': equal ranked weights; 'counts': equal symbols and counts; 'support': equal symbols, the code made from their
    pooled counts (can cost more than one bit above the entropy); 'off': none.
    """
    per = weighted.groupBy("ctx").agg(F.array_sort(F.collect_list(F.struct("w", "sym", "n"))).alias("own"))
    if cache == "support":
        sig = F.sha2(F.array_join(F.array_sort(F.transform("own", lambda x: x["sym"].cast("string"))), ",").cast("binary"), 256)
        tagged = per.select("ctx", "own", sig.alias("sig"))
        each = tagged.select("ctx", "sig", F.explode("own").alias("x"))
        pooled = each.groupBy("sig", F.col("x.sym").alias("sym")).agg(F.sum("x.n").alias("n"), F.min(F.col("x.w") - F.col("x.n")).alias("alpha"))
        code = pooled.withColumn("pw", F.col("n") + F.col("alpha")).groupBy("sig").agg(F.array_sort(F.collect_list(F.struct("pw", "sym"))).alias("p"))
        code = code.withColumn("lens", lengths_of(single_symbol)(F.transform("p", lambda x: x["pw"])))
        code = code.select("sig", F.posexplode(F.arrays_zip(F.transform("p", lambda x: x["sym"]).alias("sym"), F.col("lens").alias("len"))).alias("rank", "c"))
        code = code.select("sig", "rank", F.col("c").getField("sym").alias("sym"), F.col("c").getField("len").alias("len"))
        return each.select("ctx", "sig", "x.*").join(code, ["sig", "sym"]).select("ctx", "sym", "n", "w", "rank", "len", "sig")
    profile = F.transform("own", lambda x: x["w"])
    key = {
        "profile": F.array_join(F.transform(profile, lambda w: w.cast("string")), ","),
        "counts": F.array_join(F.array_sort(F.transform("own", lambda x: F.concat_ws(":", x["sym"].cast("string"), x["n"].cast("string")))), ","),
        "off": F.col("ctx").cast("string"),
    }[cache]
    tagged = per.select("ctx", "own", profile.alias("profile"), F.sha2(key.cast("binary"), 256).alias("sig"))
    distinct = tagged.groupBy("sig").agg(F.first("profile").alias("profile")).repartition("sig")
    coded = distinct.select("sig", lengths_of(single_symbol)("profile").alias("lens"))
    both = tagged.select("ctx", "own", "sig").join(coded, "sig")
    each = both.select("ctx", "sig", F.posexplode(F.arrays_zip("own", "lens")).alias("rank", "x"))
    return each.select("ctx", F.col("x.own.sym").alias("sym"), F.col("x.own.n").alias("n"), F.col("x.own.w").alias("w"), "rank", F.col("x.lens").alias("len"), "sig")


def canonical(coded: DataFrame) -> DataFrame:
    """Adds code, bits as text: codewords in the order (len, rank) are consecutive binary fractions. Exact while lengths stay within 52 bits."""
    w = Window.partitionBy("ctx").orderBy("len", "rank").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("len"))).over(w), F.lit(0.0))
    value = F.bin((before * F.pow(F.lit(2.0), F.col("len"))).cast("long"))
    long = F.when(F.col("len") > 52, F.raise_error("code longer than 52 bits").cast("string"))
    return coded.withColumn("code", F.coalesce(long, F.when(F.col("len") == 0, F.lit("")).otherwise(F.lpad(value, F.col("len"), F.lit("0")))))


def codebooks(weighted: DataFrame, cache: str = "profile", single_symbol: str = "empty") -> DataFrame:
    """(ctx, sym, n, w, rank, len, sig, code)."""
    return canonical(lengths(weighted, cache, single_symbol))


def verify(codebook: DataFrame) -> DataFrame:
    """(ctx, symbols, kraft, clashes): the Kraft sum, and how many codes begin like the one before them in text order (0 if prefix-free)."""
    w = Window.partitionBy("ctx").orderBy("code")
    clash = F.lead("code").over(w).startswith(F.col("code"))
    return codebook.withColumn("_c", F.coalesce(clash, F.lit(False)).cast("long")).groupBy("ctx").agg(
        F.count(F.lit(1)).alias("symbols"), F.round(F.sum(F.pow(F.lit(2.0), -F.col("len"))), 9).alias("kraft"), F.sum("_c").alias("clashes")
    )
