"""Column expressions for encodings of carrier rows; no Python runs on executors."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 64


def id_width(h: int) -> int:
    """Bits of a haplotype id in a cohort of ``h``, exact for every h; one bit for a cohort of one."""
    return max(1, (h - 1).bit_length())


def id_width_of(h: Column) -> Column:
    return F.when(h <= 1, F.lit(1)).otherwise(F.length(F.bin(h - 1))).cast("long")


def bits_dense(h: int) -> Column:
    return F.lit(h).cast("long")


def bits_list(k: Column, h: int) -> Column:
    return (k * id_width(h)).cast("long")


def bits_hybrid(k: Column, h: int) -> Column:
    return F.least(bits_dense(h), bits_list(k, h))


def row_encoding(k: Column, h: int, policy: str = "min_cost") -> Column:
    """'list' or 'bitmap' by policy; a tie of costs goes to the list."""
    if policy == "min_cost":
        sparse = bits_list(k, h) <= bits_dense(h)
    elif policy == "threshold":
        sparse = k < F.lit(h) / F.log2(F.lit(float(h))) if h > 1 else F.lit(True)
    elif policy in ("list", "bitmap"):
        return F.lit(policy)
    else:
        raise ValueError(f"unknown policy {policy}")
    return F.when(sparse, "list").otherwise("bitmap")


def popcount_words(words: Column) -> Column:
    """Empty words leave before the rest is counted one by one."""
    return F.aggregate(F.array_remove(words, F.lit(0).cast("long")), F.lit(0).cast("long"), lambda acc, w: acc + F.bit_count(w))


def and_words(x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: a.bitwiseAND(b))


def or_words(x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: a.bitwiseOR(b))


def and_not_words(x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: a.bitwiseAND(F.bitwise_not(b)))


def bit(word: Column, place: Column) -> Column:
    """0 or 1; the sign bit of a word is bit 63."""
    return F.call_function("getbit", word, place.cast("int"))


def contains_hap(words: Column, hap: Column) -> Column:
    return bit(F.get(words, F.floor(hap / WORD).cast("int")), hap % WORD) == 1


def bit_of(hap: Column) -> Column:
    """The word of 64 bits in which only the bit of ``hap`` is set."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), (hap % WORD).cast("int"))


def carriers_of_held(held: Column) -> Column:
    """Ascending ids of sorted (word_no, word) of the non-empty words."""
    places = lambda x: F.filter(F.sequence(F.lit(0), F.lit(WORD - 1)), lambda b: bit(x["word"], b) == 1)
    ids = lambda x: F.transform(places(x), lambda b: x["word_no"] * WORD + b)
    # -w has the bits of a single bit w and of all places above it; w = -2^63 has no other, and is left to the long way, as its negative overflows.
    place = lambda w: WORD - F.bit_count(w.bitwiseOR(F.bitwise_not(w) + 1)).cast("long")
    only = lambda x: F.array(x["word_no"] * WORD + place(x["word"]))
    return F.flatten(F.transform(held, lambda x: F.when((x["word"] > 0) & (F.bit_count(x["word"]) == 1), only(x)).otherwise(ids(x))))


def words_of_held(held: Column, n: int) -> Column:
    """All n words of sorted (word_no, word) of the non-empty words: zeros up to each one, and after the last."""
    zeros = lambda k: F.array_repeat(F.lit(0).cast("long"), k.cast("int"))
    at = lambda i: F.coalesce(F.get(held, i)["word_no"], F.lit(-1))
    upto = F.transform(held, lambda x, i: F.concat(zeros(x["word_no"] - at(i - 1) - 1), F.array(x["word"])))
    return F.concat(F.flatten(upto), zeros(n - 1 - at(F.size(held) - 1)))


def words_of_rest(held: Column, h: int) -> Column:
    """All words of the haplotypes of a cohort of ``h`` that are not in (word_no, word)."""
    n = -(-h // WORD)
    last = (1 << (h % WORD)) - 1 if h % WORD else -1
    full = lambda i: F.when(i == n - 1, F.lit(last).cast("long")).otherwise(F.lit(-1).cast("long"))
    return F.transform(words_of_held(held, n), lambda w, i: full(i).bitwiseAND(F.bitwise_not(w)))


def carriers_of_words(words: Column) -> Column:
    """Ascending ids of the set bits; empty words cost nothing."""
    numbered = F.transform(words, lambda w, i: F.struct(i.cast("long").alias("word_no"), w.alias("word")))
    return carriers_of_held(F.filter(numbered, lambda x: x["word"] != 0))


def words_touched(k: Column, enc: Column, h: int) -> Column:
    """Ids or words that a scan of the row reads."""
    return F.when(enc == "list", k).otherwise(F.lit(-(-h // WORD))).cast("long")


def varint_length(ids: Column) -> Column:
    """Bytes that :func:`varint_bytes` writes."""
    step = lambda x, i: x - F.coalesce(F.get(ids, i - 1), F.lit(0))
    more = lambda s: reduce(lambda a, n: a + (s >= 1 << 7 * n).cast("int"), range(1, 9), F.lit(1))
    return F.aggregate(F.transform(ids, lambda x, i: more(step(x, i))), F.lit(0).cast("long"), lambda acc, n: acc + n)


def varint_bytes(ids: Column) -> Column:
    """Ascending ids as bytes: the step from each id to the next (the first from zero) in groups of seven bits, lowest first; the high bit says that more follow."""
    steps = F.transform(ids, lambda x, i: x - F.coalesce(F.get(ids, i - 1), F.lit(0)))

    shift = lambda way, x, n: F.call_function(f"shift{way}", x, F.lit(n) if isinstance(n, int) else n)

    def groups(step: Column) -> Column:
        last = F.greatest(F.lit(1), F.ceil(F.length(F.bin(step)) / 7)).cast("int") - 1
        one = lambda j: step.bitwiseAND(shift("left", F.lit(127).cast("long"), 7 * j))
        byte = lambda j: shift("right", one(j), 7 * j) + F.when(j < last, 128).otherwise(0)
        long = F.array_join(F.transform(F.sequence(F.lit(0), last), lambda j: F.lpad(F.hex(byte(j)), 2, "0")), "")
        out = F.when(step < 1 << 7, F.lpad(F.hex(step), 2, "0"))
        for n in (2, 3, 4):  # up to four bytes as the digits of one number, whose first byte has its high bit
            parts = [shift("left", shift("right", step, 7 * j).bitwiseAND(127).bitwiseOR(128 if j < n - 1 else 0), 8 * (n - 1 - j)) for j in range(n)]
            out = out.when(step < 1 << 7 * n, F.hex(reduce(lambda a, b: a.bitwiseOR(b), parts)))
        return out.otherwise(long)

    return F.unhex(F.array_join(F.transform(steps, groups), ""))


def varint_steps(packed: Column) -> Column:
    """The steps that :func:`varint_bytes` wrote; their running sums are the ids."""
    each = F.regexp_extract_all(F.hex(packed), F.lit("((?:[89A-F][0-9A-F])*[0-7][0-9A-F])"), F.lit(1))

    def value(text: Column) -> Column:
        part = lambda j: F.conv(F.substr(text, 2 * j + 1, F.lit(2)), 16, 10).cast("long").bitwiseAND(127)
        places = F.sequence(F.lit(0), F.floor(F.length(text) / 2).cast("int") - 1)
        long = F.aggregate(places, F.lit(0).cast("long"), lambda acc, j: acc + F.call_function("shiftleft", part(j), 7 * j))
        whole, out = F.conv(text, 16, 10).cast("long"), None
        for n in (1, 2, 3, 4):
            parts = [F.call_function("shiftleft", F.call_function("shiftright", whole, F.lit(8 * (n - 1 - j))).bitwiseAND(127), F.lit(7 * j)) for j in range(n)]
            x = reduce(lambda a, b: a.bitwiseOR(b), parts)
            out = F.when(F.length(text) == 2, x) if out is None else out.when(F.length(text) == 2 * n, x)
        return out.otherwise(long)

    return F.transform(each, value)
