"""Set queries on carrier rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import bitops as B
from . import rows as R


def carriers(rows: DataFrame, alleles: list) -> DataFrame:
    """(allele_id, hap_id) of the named alleles; the key filter reaches the scan."""
    return R.decode(rows.where(F.col("allele_id").isin(list(alleles))))


def frequency(rows: DataFrame, h: int) -> DataFrame:
    """(allele_id, k, af); k is stored beside each row, so no payload is read."""
    return rows.select("allele_id", "k", (F.col("k") / h).alias("af"))


def frequency_by_popcount(rows: DataFrame, h: int) -> DataFrame:
    """The same from the payload alone."""
    k = F.when(F.col("enc") == "list", F.size("carriers")).otherwise(B.popcount_words(F.col("words"))).cast("long")
    return rows.select("allele_id", k.alias("k"), (k / h).alias("af"))


def _pair(rows: DataFrame, a, b) -> DataFrame:
    one = lambda key, p: rows.where(F.col("allele_id") == key).select(F.lit(0).alias("_j"), *(F.col(c).alias(f"{p}_{c}") for c in ("k", "enc", "carriers", "words")))
    return one(a, "x").join(F.broadcast(one(b, "y")), "_j")  # one row on each side


def _listed(p: str) -> Column:
    return F.when(F.col(f"{p}_enc") == "list", F.col(f"{p}_carriers")).otherwise(B.carriers_of_words(F.col(f"{p}_words")))


def _worded(p: str, h: int) -> Column:
    n = -(-h // B.WORD)
    ids = F.col(f"{p}_carriers")
    word = lambda i: F.aggregate(F.filter(ids, lambda x: F.floor(x / B.WORD) == i), F.lit(0).cast("long"), lambda acc, x: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), (x % B.WORD).cast("int"))))
    built = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")), word)
    return F.when(F.col(f"{p}_enc") == "bitmap", F.col(f"{p}_words")).otherwise(built)


def intersect(rows: DataFrame, a, b, h: int, how: str = "auto") -> DataFrame:
    """(a, b, hap_id) carried by both: 'merge' of lists, 'and' of words, 'probe' of the smaller in the larger, or the cheapest of them."""
    pair = _pair(rows, a, b)
    x_small = F.col("x_k") <= F.col("y_k")
    merged = F.array_intersect(_listed("x"), _listed("y"))
    anded = B.carriers_of_words(B.and_words(_worded("x", h), _worded("y", h)))
    inside = lambda p: lambda hap: F.when(F.col(f"{p}_enc") == "list", F.array_contains(f"{p}_carriers", hap)).otherwise(B.contains_hap(F.col(f"{p}_words"), hap))
    probed = F.when(x_small, F.filter(_listed("x"), inside("y"))).otherwise(F.filter(_listed("y"), inside("x")))
    both = lambda e: (F.col("x_enc") == e) & (F.col("y_enc") == e)
    auto = F.when(both("list"), merged).when(both("bitmap"), anded).otherwise(probed)
    found = {"merge": merged, "and": anded, "probe": probed, "auto": auto}[how]
    return pair.select(F.lit(a).alias("a"), F.lit(b).alias("b"), F.explode(found).alias("hap_id"))


def touched(rows: DataFrame, a, b, h: int) -> DataFrame:
    """Ids or words that each strategy reads for a pair of alleles."""
    pair, w = _pair(rows, a, b), -(-h // B.WORD)
    read = lambda p: B.words_touched(F.col(f"{p}_k"), F.col(f"{p}_enc"), h)
    return pair.select((read("x") + read("y")).alias("stored"), (F.col("x_k") + F.col("y_k")).alias("merge"), F.lit(2 * w).cast("long").alias("and"), F.least("x_k", "y_k").alias("probe"))


def combine(inc: DataFrame, alleles: list, how: str, h: int | None = None) -> DataFrame:
    """(hap_id) of the union, the difference (the first without the others), or the complement of the union."""
    own = inc.where(F.col("allele_id").isin(list(alleles))).select("allele_id", "hap_id")
    if how == "union":
        return own.select("hap_id").distinct()
    if how == "difference":
        return own.where(F.col("allele_id") == alleles[0]).select("hap_id").distinct().join(own.where(F.col("allele_id") != alleles[0]).select("hap_id"), "hap_id", "left_anti")
    return inc.sparkSession.range(h).select(F.col("id").alias("hap_id")).join(own.select("hap_id"), "hap_id", "left_anti")


def cohort_filter(rows: DataFrame, require=(), exclude=(), any_of=(), early_stop: bool = False, h: int | None = None) -> DataFrame:
    """(hap_id) carrying all required alleles, none excluded and at least one of ``any_of``; of all ``h`` haplotypes if neither is given.

    The required alleles are taken from rare to frequent, by their stored counts; with ``early_stop``
    an empty intermediate result ends the chain.
    """
    require = list(dict.fromkeys(require))
    k = {r["allele_id"]: r["k"] for r in rows.where(F.col("allele_id").isin(list(require))).select("allele_id", "k").collect()} if require else {}
    order = sorted(require, key=lambda a: (k.get(a, 0), str(a)))
    haps = lambda names: carriers(rows, names).select("hap_id")
    out = None
    if early_stop:
        for a in order:
            out = haps([a]) if out is None else out.join(haps([a]), "hap_id", "left_semi")
            if out.isEmpty():
                return out
    elif order:  # one pass: all required alleles at once
        out = carriers(rows, order).groupBy("hap_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == len(order)).select("hap_id")
    if any_of:
        some = haps(any_of).distinct()
        out = some if out is None else out.join(some, "hap_id", "left_semi")
    if out is None:
        if h is None:
            raise ValueError("without required alleles the size of the cohort is needed")
        out = rows.sparkSession.range(h).select(F.col("id").alias("hap_id"))
    if exclude:
        out = out.join(haps(exclude), "hap_id", "left_anti")
    return out


def co_carriage(inc: DataFrame, kept: DataFrame | None = None) -> DataFrame:
    """(a, b, n) for pairs a < b of alleles with common carriers. Filter the alleles (``kept``) first: a haplotype with m of them makes m^2/2 pairs."""
    own = inc.select("allele_id", "hap_id").distinct()
    if kept is not None:
        own = own.join(kept.select("allele_id"), "allele_id", "left_semi")
    x, y = own.select(F.col("allele_id").alias("a"), "hap_id"), own.select(F.col("allele_id").alias("b"), "hap_id")
    return x.join(y, "hap_id").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


def stratify(inc: DataFrame, cohort: DataFrame, by: str) -> DataFrame:
    """(allele_id, stratum, k, h_stratum, af); ``cohort`` has (hap_id, stratum columns)."""
    sizes = cohort.groupBy(F.col(by).alias("stratum")).agg(F.count(F.lit(1)).alias("h_stratum"))
    pairs = inc.select("allele_id", "hap_id").distinct().join(cohort.select("hap_id", F.col(by).alias("stratum")), "hap_id")
    return pairs.groupBy("allele_id", "stratum").agg(F.count(F.lit(1)).alias("k")).join(sizes, "stratum").select("allele_id", "stratum", "k", "h_stratum", (F.col("k") / F.col("h_stratum")).alias("af"))


def private(inc: DataFrame, cohort: DataFrame, by: str) -> DataFrame:
    """(allele_id, stratum, k) of alleles carried in one stratum only."""
    pairs = inc.select("allele_id", "hap_id").distinct().join(cohort.select("hap_id", F.col(by).alias("stratum")), "hap_id")
    return pairs.groupBy("allele_id").agg(F.min("stratum").alias("stratum"), F.max("stratum").alias("_z"), F.count(F.lit(1)).alias("k")).where(F.col("stratum").eqNullSafe(F.col("_z"))).drop("_z")


def rare(counted: DataFrame, h: int, max_af: float | None = None, max_k: int | None = None) -> DataFrame:
    tests = [F.col("k") <= max_k] if max_k is not None else []
    tests += [F.col("k") < F.lit(max_af) * h] if max_af is not None else []
    return counted.where(reduce(lambda a, b: a & b, tests, F.lit(True)))


def rarity(counted: DataFrame, h: int, by: str = "class") -> DataFrame:
    """Shares of rows with at most two carriers and with frequency below 10 %."""
    return counted.groupBy(by).agg(
        F.count(F.lit(1)).alias("n_rows"), F.round(F.avg((F.col("k") <= 2).cast("double")), 6).alias("share_k2"), F.round(F.avg((F.col("k") * 10 < h).cast("double")), 6).alias("share_af10"),
    )


def spectrum(counted: DataFrame, h: int, bins: int = 20) -> DataFrame:
    """(bin, n_rows): frequency bins of equal width, the last one closed."""
    at = F.least(F.floor(F.col("k") * bins / h), F.lit(bins - 1)).cast("long")
    return counted.groupBy(at.alias("bin")).agg(F.count(F.lit(1)).alias("n_rows"))


def burden(inc: DataFrame, kept: DataFrame | None = None) -> DataFrame:
    """(hap_id, n): alleles of each haplotype, of the kept alleles only if given."""
    own = inc.select("allele_id", "hap_id").distinct()
    if kept is not None:
        own = own.join(kept.select("allele_id"), "allele_id", "left_semi")
    return own.groupBy("hap_id").agg(F.count(F.lit(1)).alias("n"))
