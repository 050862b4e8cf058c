"""Entropy, expected and realized code length, redundancy; beside what other coders would spend."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import markov, prefix


def contexts(codebook: DataFrame) -> DataFrame:
    """(ctx, events, alphabet, h, l, gap) under the smoothed distribution over the coded symbols."""
    total = F.sum("w").over(Window.partitionBy("ctx"))
    p = F.when(total > 0, F.col("w") / total).otherwise(0.0)
    plogp = F.when(F.col("p") > 0, -F.col("p") * F.log2("p")).otherwise(0.0)
    out = codebook.withColumn("p", p).groupBy("ctx").agg(
        F.sum("n").cast("long").alias("events"), F.count(F.lit(1)).alias("alphabet"), F.sum(plogp).alias("h"), F.sum(F.col("p") * F.col("len")).alias("l")
    )
    return out.withColumn("gap", F.col("l") - F.col("h"))


def global_(codebook: DataFrame, min_events: int = 10) -> DataFrame:
    """One row: sizes, H and L weighted by the events of contexts with at least ``min_events``, the realized rate over all, the ratio to 32 bits, violations of H <= L < H + 1."""
    per = contexts(codebook)
    kept = F.col("events") >= min_events
    avg = lambda c: F.sum(F.when(kept, F.col("events") * F.col(c))) / F.sum(F.when(kept, F.col("events")))
    bad = (F.col("l") >= F.col("h") + 1) | (F.col("l") < F.col("h") - 1e-9)
    top = per.agg(
        F.sum(kept.cast("long")).alias("contexts_kept"), F.count(F.lit(1)).alias("contexts_all"), F.sum(F.when(kept, F.col("events")).otherwise(0)).cast("long").alias("events_kept"),
        F.round(avg("h"), 6).alias("h_global"), F.round(avg("l"), 6).alias("l_global"), F.round(avg("l") - avg("h"), 6).alias("redundancy"), F.sum(bad.cast("long")).alias("bound_violations"),
    )
    rate = F.sum(F.col("n") * F.col("len")) / F.sum("n")
    real = codebook.agg(F.sum("n").cast("long").alias("symbols"), F.round(rate, 6).alias("realized"), F.round(32 / rate, 6).alias("ratio32"))
    return top.crossJoin(F.broadcast(real))  # one row each


def comparison(codebook: DataFrame, single_symbol: str = "empty") -> DataFrame:
    """(coder, bits): bits per symbol of the context code, of the naive Markov coder, the ideal, one code without contexts, and fixed widths."""
    total = F.sum("w").over(Window.partitionBy("ctx"))
    own = codebook.withColumn("lp", F.when(F.col("w") > 0, -F.log2(F.col("w") / total)))
    n = F.sum("n")
    naive = F.ceil(F.round("lp", 9))
    rates = own.agg((F.sum(F.col("n") * F.col("len")) / n).alias("context_prefix"), (F.sum(F.col("n") * naive) / n).alias("naive_markov"), (F.sum(F.when(F.col("n") > 0, F.col("n") * F.col("lp"))) / n).alias("ideal"))
    symbols = codebook.groupBy("sym").agg(n.cast("long").alias("n")).where("n > 0")
    flat = prefix.lengths(symbols.select(F.lit(0).cast("long").alias("ctx"), "sym", "n", F.col("n").cast("double").alias("w")), single_symbol=single_symbol)
    order0 = flat.agg((F.sum(F.col("n") * F.col("len")) / n).alias("order0"))
    nodes = symbols.where(F.col("sym") >= 0).agg(F.count(F.lit(1)).alias("v"))
    fixed = nodes.select(F.length(F.bin("v")).cast("double").alias("fixed_min"))  # width of v + 1 symbols
    one = rates.crossJoin(order0).crossJoin(fixed).withColumn("fixed32", F.lit(32.0))
    coders = ["context_prefix", "naive_markov", "ideal", "order0", "fixed_min", "fixed32"]
    return one.select(F.explode(F.array(*[F.struct(F.lit(c).alias("coder"), F.round(F.col(c), 6).alias("bits")) for c in coders])).alias("x")).select("x.*")


def full_alphabet(codebook: DataFrame, alpha: float = 1.0) -> DataFrame:
    """One row: contexts x symbols that smoothing over the whole alphabet would code, against the observed pairs, and its mean entropy; nothing of that size is built."""
    v = codebook.agg(F.countDistinct("sym").alias("v"), F.count(F.lit(1)).alias("observed"), F.countDistinct("ctx").alias("contexts"))
    per = codebook.groupBy("ctx").agg(F.sum("n").alias("events"), F.sum((F.col("n") > 0).cast("long")).alias("seen"), F.sum(F.when(F.col("n") > 0, (F.col("n") + alpha) * F.log2(F.col("n") + alpha)).otherwise(0.0)).alias("s"))
    a = per.crossJoin(F.broadcast(v))
    t = F.col("events") + alpha * F.col("v")
    rest = (F.col("v") - F.col("seen")) * alpha * (math.log2(alpha) if alpha > 0 else 0.0)
    h = F.log2(t) - (F.col("s") + rest) / t
    return a.agg(F.max("contexts").alias("contexts"), (F.max("contexts") * F.max("v")).alias("coded_pairs"), F.max("observed").alias("observed_pairs"), F.round(F.sum(F.col("events") * h) / F.sum("events"), 6).alias("h_full"))


def fit_size(codebook: DataFrame) -> DataFrame:
    """One row: symbols, contexts, distinct transitions and signatures, and the share of contexts that reuse a code."""
    per = codebook.groupBy("ctx").agg(F.sum("n").alias("n"), F.sum((F.col("n") > 0).cast("long")).alias("seen"), F.min("sig").alias("sig"))  # a context has one code
    by_sig = per.groupBy("sig").agg(F.sum("n").alias("n"), F.sum("seen").alias("seen"), F.count(F.lit(1)).alias("c"))
    total, c, s = (lambda x: F.sum(x).cast("long")), F.sum("c"), F.count("sig")
    return by_sig.agg(total("n").alias("symbols"), c.alias("contexts"), total("seen").alias("transitions"), s.alias("signatures"), F.round(1 - s / c, 6).alias("reused"))


__all__ = ["comparison", "contexts", "fit_size", "full_alphabet", "global_", "markov"]
