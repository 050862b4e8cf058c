"""Document fingerprints by MinHash.

Words are runs of anything but white space in the text with A-Z in lower case; a shingle is five
words in a row, or the whole text if it has fewer. Shingles are hashed with numpy, all of a text at once: a
prefix sum of a polynomial in the bytes gives every word's hash, five word hashes
mix into a shingle's. ``HASHES`` multiply-shift permutations over the shingle hashes give the
signature; of each minimum the lowest 16 bits are kept, which agree by chance once in 65,536.

Near duplicates: ``BANDS`` bands of signature rows are joined in Spark, and the Jaccard
similarity of the shingle sets of candidates is verified. Equal sets are one document
in the join, and no band is expanded into all pairs (:mod:`links`).

Null texts count as empty; texts without words have the empty fingerprint, which is
like another empty one (1) and unlike all others (0), and are near duplicates of nothing; equal texts have
equal fingerprints; repeated rows get a row each; texts of any length are read whole.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, partitions, text_of

WORDS, HASHES, BANDS = 5, 128, 32
#: Shingle hashes that go through all permutations at once.
_BLOCK = 1 << 13
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_U = np.uint64


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads all bits (the finalizer of splitmix64)."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_INVERSE = pow(int(_BASE), -1, 1 << 64)
_powers = np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64 up to n."""
    global _powers
    if len(_powers[0]) < n:
        n = max(n, 1 << 16)
        _powers = tuple(np.concatenate([[_U(1)], np.multiply.accumulate(np.full(n, b, dtype=np.uint64))]) for b in (_BASE, _U(_INVERSE)))
    return _powers


def word_hashes(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(hash, start) of each word of UTF-8 bytes."""
    raw = np.frombuffer(data, dtype=np.uint8)
    space = _IS_SPACE[raw]
    edge = np.flatnonzero(np.diff(np.concatenate([[True], space, [True]]).astype(np.int8)))
    start, end = edge[::2], edge[1::2]
    up, down = _power_tables(len(raw) + 1)
    sums = np.concatenate([[_U(0)], np.cumsum((_LOWER[raw].astype(np.uint64) + _U(1)) * up[: len(raw)], dtype=np.uint64)])
    return _mixed((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64)), start


def shingle_hashes(words: np.ndarray, n: int = WORDS) -> np.ndarray:
    """Hashes of all runs of n words in order, or of the whole sequence if it is shorter and not empty."""
    if not len(words):
        return words
    k = min(n, len(words))
    out = np.full(len(words) - k + 1, _U(k), dtype=np.uint64)
    for i in range(k):
        out = _mixed(out * _U(0x9E3779B97F4A7C15) + words[i : len(words) - k + 1 + i])
    return out


def shingles(text: str, n: int = WORDS) -> np.ndarray:
    return shingle_hashes(word_hashes(text.encode("utf-8", "surrogatepass"))[0], n)


def shingle_sets(texts: list[str], n: int = WORDS) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    for t in texts:
        yield np.unique(shingles(t, n))


class Permutations:
    """Multiply-shift permutations of 64-bit hashes, the high 32 bits kept."""

    def __init__(self, hashes: int = HASHES, seed: int = 1):
        rng = np.random.default_rng(seed)
        self.a = rng.integers(0, 1 << 63, size=(hashes, 1), dtype=np.uint64) * _U(2) + _U(1)
        self.b = rng.integers(0, 1 << 63, size=(hashes, 1), dtype=np.uint64)

    def signature(self, hashes: np.ndarray) -> np.ndarray:
        """Low 16 bits of the least value of each permutation; no entries for no shingles."""
        if not len(hashes):
            return np.zeros(0, dtype=np.uint16)
        low = np.full(len(self.a), np.iinfo(np.uint64).max, dtype=np.uint64)
        for at in range(0, len(hashes), _BLOCK):
            low = np.minimum(low, (self.a * hashes[at : at + _BLOCK] + self.b).min(axis=1))
        return (low >> _U(32)).astype(np.uint16)


def alike(x: np.ndarray, y: np.ndarray) -> float:
    """Share of equal rows of two signatures."""
    if not len(x) or not len(y):
        return float(len(x) == len(y))
    return float((x == y).mean())


def as_text(signature: np.ndarray) -> str:
    return base64.b64encode(signature.astype("<u2").tobytes()).decode()


def from_text(fingerprint: str) -> np.ndarray:
    return np.frombuffer(base64.b64decode(fingerprint), dtype="<u2")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hashes: int = HASHES) -> DataFrame:
    """(doc_id, n_chars, fingerprint) of every row."""

    def run(batches):
        perms = Permutations(hashes)
        for b in batches:
            texts = b.column(1).to_pylist()
            prints = [as_text(perms.signature(shingles(t))) for t in texts]
            yield pa.record_batch([b.column(0), pa.array(list(map(len, texts)), pa.int64()), pa.array(prints, pa.string())], names=["doc_id", "n_chars", "fingerprint"])

    rows = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text"))
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, n_chars long, fingerprint string")


# Fingerprints beside those of an edited text ------------------------------------------


def in_ranges(docs: DataFrame, ranges: int) -> DataFrame:
    """Rows (doc_id, text) with the range of ids that needs them, sorted by it.

    Each row goes to its own range; the first row of a range goes to the range before
    it as well (``after`` is true there), and the very first row to the last range, so
    that each range holds the next row of all its rows. The ends of the ranges are ids that exist.
    """
    ids = docs.where(F.col("doc_id").isNotNull())
    step = [i / ranges for i in range(1, ranges)]
    found = ids.agg(F.min("doc_id").alias("least"), F.percentile_approx("doc_id", step, 100 * ranges).alias("ends") if step else F.array().alias("ends")).first()
    least = found["least"]
    ends = sorted({e for e in found["ends"] or [] if e != least})  # at most ``ranges`` ids
    if least is None:
        own = F.lit(0)
    else:
        own = F.lit(0) if not ends else F.size(F.filter(F.array(*[F.lit(e) for e in ends]), lambda e: e <= F.col("doc_id")))
    place = F.when(F.col("doc_id").isNull(), F.lit(0)).otherwise(own)
    copies = F.array(F.struct(place.alias("range"), F.lit(False).alias("after")))
    if least is not None:
        heads = [least, *ends]
        is_head = F.col("doc_id").isin(heads)
        before = F.when(F.col("doc_id") == F.lit(least), F.lit(len(ends))).otherwise(place - 1)
        copies = F.when(is_head, F.concat(copies, F.array(F.struct(before.alias("range"), F.lit(True).alias("after"))))).otherwise(copies)
    spread = docs.select("doc_id", "text", F.explode(copies).alias("c")).select("c.range", "c.after", "doc_id", "text")
    return spread.repartition(ranges, "range").sortWithinPartitions("range", "after", "doc_id", "text")


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hashes: int = HASHES) -> DataFrame:
    """Every row with its fingerprint, that of its edited text and that of the next row, by ascending id.

    The edited text has its last floor(n_chars / 4) code points replaced by the first as many (or all) of
    the next text; after the last row comes the first. Null ids come before all others.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))
    spread = in_ranges(rows, max(1, partitions(docs.sparkSession)))
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]

    def run(batches):
        perms = Permutations(hashes)

        def stream():
            for b in batches:
                yield from zip(*(c.to_pylist() for c in b.columns), strict=True)

        def edit(row, following):
            (doc_id, text, sig), (_, other, other_sig) = row, following
            k = len(text) // 4
            edited = text[: len(text) - k] + other[:k] if k else text
            edited_sig = perms.signature(shingles(edited)) if k else sig
            return (doc_id, len(text), hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest(), as_text(sig), as_text(edited_sig), alike(sig, edited_sig), alike(sig, other_sig))

        out, held, at, done = [], None, None, False
        for number, after, doc_id, text in stream():
            if number != at:
                held, at, done = None, number, False
            if done:
                continue
            row = (doc_id, text, perms.signature(shingles(text)))
            if held is not None:
                out.append(edit(held, row))
            held, done = row, after  # the row after a range ends it
            if len(out) >= 1024:
                yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)
                out = []
        if out:
            yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    return spread.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


# Near duplicates ------------------------------------------------------------------------


def band_lists(docs: DataFrame, hashes: int = HASHES, bands: int = BANDS) -> DataFrame:
    """(doc, key, bands) of every row (doc, text): a digest of its set and one of each band of its signature."""
    rows = hashes // bands

    def run(batches):
        perms = Permutations(hashes)
        for b in batches:
            keys, every = [], []
            for own in shingle_sets(b.column(1).to_pylist()):
                sig = perms.signature(own)
                keys.append(hashlib.blake2b(own.tobytes(), digest_size=16).digest())
                every.append([hashlib.blake2b(bytes([k]) + sig[k * rows : (k + 1) * rows].tobytes(), digest_size=12).digest() for k in range(bands)] if len(sig) else [])
            yield pa.record_batch([b.column(0), pa.array(keys, pa.binary()), pa.array(every, pa.list_(pa.binary()))], names=["doc", "key", "bands"])

    return docs.mapInArrow(run, "doc long, key binary, bands array<binary>")


def near_duplicates(docs: DataFrame, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", hashes: int = HASHES, bands: int = BANDS) -> DataFrame:
    """(doc_id, class_id): the least id reachable by verified links between documents that share a band."""
    from .links import classes
    from .ngram_join import whole_sets

    texts = docs.select(F.col(id_col).cast("long").alias("doc"), text_of(text_col).alias("text"))
    signed = cut(band_lists(texts, hashes, bands))
    reps = signed.where(F.size("bands") > 0).groupBy("key").agg(F.min(F.struct("doc", "bands")).alias("r")).select("key", "r.doc", "r.bands")
    lists = reps.select("doc", F.explode("bands").alias("band"))
    shared = lists.groupBy("band").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("band")
    lists = cut(lists.join(shared, "band", "left_semi").select(F.col("band").alias("key"), "doc"))
    sets = cut(whole_sets(texts.join(lists.select("doc").distinct(), "doc", "left_semi")).dropDuplicates(["doc"]))
    named = reps.select("key", "doc").join(classes(lists, sets, percent), "doc", "left").select("key", F.coalesce("class", "doc").alias("class_id"))
    return signed.select("doc", "key").join(named, "key", "left").select(F.col("doc").alias("doc_id"), F.coalesce("class_id", "doc").alias("class_id"))
