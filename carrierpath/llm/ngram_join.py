"""N-gram Jaccard self-join of documents, exact, by T-occurrence search over inverted lists.

A document's set is its distinct shingles of five words (A-Z in lower case); two documents link when
their sets have a Jaccard similarity of 0.8 or more. Every similar partner has at least
``need(n)`` of a document's n shingles, which leaves few documents to look at:

1. Extended prefixes: of the shingles in the order of their hashes, the first n - need(n) + l of
   two partners share at least l. Which of them stand in more than one document is
   counted with every task sending each hash once, however frequent; documents with fewer
   than l shared ones have no partner.
2. Among the rest, shingles are ordered from rare to frequent, and only the first n - need(n) + 1 of
   each document become inverted lists: common passages stay out of them unless a document is little else.
3. Documents of common lists meet in blocks, whose whole sets become inverted lists that are searched
   for partners (:mod:`links`): short lists are merged, long
   ones probed by binary search, with the overlap that is required.

Documents with equal sets are one document in steps 2 and 3. Null and empty texts have no
shingles and link with nothing; repeated rows and copies are in one class; ties do not exist
as all comparisons are of integers; texts of any length are read whole.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.memory import trimmed
from .common import cut, one_of_each_key, partitions, row_key, sized, text_of
from .links import classes
from .minhash import WORDS, shingle_sets

PERCENT = 80
#: Extra prefix shingles that partners must share, in percent of a set.
EXTRA = 10
#: Shingle hashes whose prefixes are counted together in a task.
CHUNK = 1 << 21
#: Most ids of documents with possible partners that are broadcast; with more, the texts are shuffled to meet them.
BROADCAST_IDS = 2_000_000


def need(n: int, percent: int = PERCENT) -> int:
    """Least overlap of a set of n shingles with any partner."""
    return -(-percent * n // 100)


def extra(n: int, percent: int = EXTRA) -> int:
    return max(1, percent * n // 100)


def set_key(hashes: np.ndarray) -> bytes:
    return hashlib.blake2b(hashes.tobytes(), digest_size=16).digest()


def described(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc, n, key): the number of shingles of each row and a digest of the set; and the string column row if ``docs`` has it."""
    more = docs.columns[2:]

    def run(batches):
        for b in batches:
            sizes, keys = [], []
            for own in shingle_sets(b.column(1).to_pylist(), words):
                sizes.append(len(own))
                keys.append(set_key(own))
            yield pa.record_batch([b.column(0), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), *b.columns[2:]], names=["doc", "n", "key", *more])

    return docs.mapInArrow(trimmed(run), ", ".join(["doc long, n long, key binary", *(f"{c} string" for c in more)]))


#: What the tasks of the prefix count send each other: for a bucket of hashes, hashes and documents; for a bucket
#: of documents (from -1 downwards), documents and counts, and sizes and set digests where they are told.
_PACKED = "bucket long, a binary, b binary, sizes binary, keys binary"


def _packed(rows) -> pa.RecordBatch:
    kinds = (pa.int64(), *[pa.binary()] * 4)
    return pa.record_batch([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["bucket", "a", "b", "sizes", "keys"])


def _parted(bucket: np.ndarray, *columns: np.ndarray):
    """(bucket, parts of the columns) for each bucket that occurs."""
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    first = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
    return zip(bucket[first].tolist(), *[np.split(c[order], first[1:]) for c in columns], strict=True)


def _runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where runs of equal sorted values begin, and their lengths."""
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]]))
    return first, np.diff(np.append(first, len(values)))


def candidates(docs: DataFrame, words: int = WORDS, percent: int = PERCENT, more: int = EXTRA) -> DataFrame:
    """(doc, key) of the documents, one for each different set, that may have a partner.

    Three passes over packed arrays: tasks send each hash of their prefixes once, with the document or -1 if
    several have it; buckets of hashes find what several tasks or documents have, and count
    it by document; buckets of documents add up. Rows of a set that a task has seen already are not sent again.
    """
    buckets = partitions(docs.sparkSession)

    def send(batches):
        seen: set[bytes] = set()
        ids, sizes, keys, prefixes = [], [], [], []
        held = 0

        def flush():
            nonlocal held
            hashes = np.concatenate(prefixes)
            owner = np.repeat(np.arange(len(ids)), [len(p) for p in prefixes])
            order = np.argsort(hashes, kind="stable")
            hashes, owner = hashes[order], owner[order]
            first, count = _runs(hashes)
            local = np.bincount(owner[np.repeat(count > 1, count)], minlength=len(ids)).astype(np.int64)
            number = np.asarray(ids, dtype=np.int64)
            whose = np.where(count > 1, -1, number[owner[first]])
            sent = hashes[first]
            rows = [(k, h.tobytes(), w.tobytes(), None, None) for k, h, w in _parted((_scrambled(sent) % np.uint64(buckets)).astype(np.int64), sent, whose)]
            own = np.array(keys, dtype="S16").view(np.uint8).reshape(len(ids), 16) if ids else np.zeros((0, 16), np.uint8)
            rows += [(k, d.tobytes(), c.tobytes(), n.tobytes(), o.tobytes()) for k, d, c, n, o in _parted(-1 - number % buckets, number, local, np.asarray(sizes, dtype=np.int64), own)]
            for x in (ids, sizes, keys, prefixes):
                x.clear()
            held = 0
            return _packed(rows)

        for b in batches:
            for doc, own in zip(b.column(0).to_pylist(), shingle_sets(b.column(1).to_pylist(), words), strict=True):
                n = len(own)
                if not n or (key := set_key(own)) in seen:
                    continue
                if len(seen) < 1 << 18:
                    seen.add(key)
                ids.append(doc)
                sizes.append(n)
                keys.append(key)
                prefixes.append(own[: min(n, n - need(n, percent) + extra(n, more))])
                held += len(prefixes[-1])
                if held >= CHUNK:
                    yield flush()
        if ids:
            yield flush()

    def by_bucket(batches):
        at, parts = None, []
        for b in batches:
            for bucket, *row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if bucket != at and parts:
                    yield at, parts
                    parts = []
                at = bucket
                parts.append(row)
        if parts:
            yield at, parts

    def joined(parts, i, kind=np.int64):
        return np.concatenate([np.frombuffer(p[i], dtype=kind) for p in parts if p[i] is not None])

    def meet(batches):
        for bucket, parts in by_bucket(batches):
            if bucket < 0:
                yield _packed([(bucket, *p) for p in parts])
                continue
            hashes, docs_ = joined(parts, 0, np.uint64), joined(parts, 1)
            order = np.argsort(hashes, kind="stable")
            _, n = _runs(hashes[order])
            docs_ = docs_[order][np.repeat(n > 1, n)]
            docs_, n = np.unique(docs_[docs_ >= 0], return_counts=True)
            if len(docs_):
                yield _packed([(k, d.tobytes(), c.tobytes(), None, None) for k, d, c in _parted(-1 - docs_ % buckets, docs_, n.astype(np.int64))])

    def add(batches):
        for _, parts in by_bucket(batches):
            docs_, place = np.unique(joined(parts, 0), return_inverse=True)
            shared, told = np.bincount(place, weights=joined(parts, 1)), [p for p in parts if p[2] is not None]
            known, sizes, keys = joined(told, 0), joined(told, 2), joined(told, 3, np.uint8).reshape(-1, 16)
            # The partner may be as small as need(n), and shares its own number of extra shingles.
            least = np.maximum(1, (percent * sizes + 99) // 100 * more // 100)
            alive = shared[np.searchsorted(docs_, known)] >= least
            yield pa.record_batch([pa.array(known[alive]), pa.array([k.tobytes() for k in keys[alive]], pa.binary())], names=["doc", "key"])

    packed = docs.where(F.col("doc").isNotNull()).mapInArrow(trimmed(send), _PACKED)
    met = packed.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(trimmed(meet), _PACKED)
    alive = met.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(trimmed(add), "doc long, key binary")
    return alive.groupBy("key").agg(F.min("doc").alias("doc"))


def _scrambled(h: np.ndarray) -> np.ndarray:
    """Bits for the bucket; prefixes hold small hashes only, so their high bits do not do."""
    return (h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)


def whole_sets(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc, hashes) with the sorted distinct shingle hashes of each text."""

    def run(batches):
        for b in batches:
            sets = [s.view(np.int64) for s in shingle_sets(b.column(1).to_pylist(), words)]
            for at in range(0, len(sets), 256):
                part = [np.sort(s) for s in sets[at : at + 256]]
                yield pa.record_batch([b.column(0).slice(at, len(part)), pa.array(part, pa.list_(pa.int64()))], names=["doc", "hashes"])

    return docs.mapInArrow(trimmed(run), "doc long, hashes array<long>")


def rare_first_lists(sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Inverted lists (key, doc) of the rare-first prefixes, without shingles of one document only."""
    tokens = sets.select("doc", F.size("hashes").alias("n"), F.explode("hashes").alias("h"))
    frequent = tokens.groupBy("h").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    found = tokens.join(frequent, "h").groupBy("doc", "n").agg(F.sort_array(F.collect_list(F.struct("df", "h"))).alias("own"))  # at most a document's shingles
    # Shingles of no other document come first and make no list.
    room = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1 - (F.col("n") - F.size("own"))
    return found.where(room > 0).select("doc", F.explode(F.slice(F.col("own"), F.lit(1), room.cast("int"))).alias("t")).select(F.col("t.h").alias("key"), "doc")


def labelled(texts: DataFrame, every: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc, text) with a label of each set for doc: the id, or a hash of id and text where there is no id, a negative one, or one of several sets."""
    odd = every.groupBy("doc").agg((F.min("key") != F.max("key")).alias("several")).where("doc is null or doc < 0 or several").select(F.col("doc").alias("odd"))
    odd = cut(odd)
    if odd.isEmpty():
        return texts.select("doc", "text")
    mark = odd.withColumn("marked", F.lit(True))
    marked = texts.select("doc", "text").join(sized(mark, BROADCAST_IDS), F.col("doc").eqNullSafe(F.col("odd")), "left")
    seed = 0
    while True:
        label = F.when(F.col("marked"), F.shiftrightunsigned(F.xxhash64(F.lit(seed), "doc", "text"), 1)).otherwise(F.col("doc"))
        own = marked.select(label.alias("doc"), "text")
        if described(own, words).groupBy("doc").agg((F.min("key") != F.max("key")).alias("several")).where("several").isEmpty():
            return own
        seed += 1


def row_classes(texts: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """(doc, n, key, root, component) and row if given, for each row of (doc, text) or (doc, text, row): root tells classes apart, component is the least id of the class."""
    every = cut(described(texts, words))
    texts = labelled(texts, every, words)
    alive = cut(candidates(texts, words, percent))
    sets = cut(whole_sets(texts.join(sized(alive.select("doc"), BROADCAST_IDS), "doc", "left_semi"), words).dropDuplicates(["doc"]))
    lists = cut(rare_first_lists(sets, percent))
    linked = classes(lists, sets, percent)
    # Classes of sets: every row with the set of a linked document belongs to its class, which the least of its sets names.
    of_class = cut(alive.join(linked, "doc").select("key", "class"))
    named = of_class.groupBy("class").agg(F.min("key").alias("root"))
    of_key = of_class.join(named, "class").select("key", "root")
    least = every.where("n > 0").groupBy("key").agg(F.min("doc").alias("own"))
    of_key = least.join(of_key, "key", "left").withColumn("root", F.coalesce("root", "key"))
    roots = of_key.groupBy("root").agg(F.min("own").alias("component"))
    return every.join(of_key.join(roots, "root").select("key", "root", "component"), "key", "left")


def join_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id), one row per row of ``docs``."""
    rows = row_classes(docs.select(F.col(id_col).cast("long").alias("doc"), text_of(text_col).alias("text")), words, percent)
    return rows.select(
        F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component")).otherwise(F.col("doc")).alias("component_id")
    )


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **params) -> DataFrame:
    """The rows of ``docs`` that stay: of each class one row with the least id, and one without an id only if none has one; of rows without shingles one of each id and text."""
    keyed = docs.withColumn("_row", row_key(F.col(id_col), F.col(text_col)))
    rows = cut(row_classes(keyed.select(F.col(id_col).cast("long").alias("doc"), text_of(text_col).alias("text"), F.col("_row").alias("row")), **params))
    kept = rows.where("n > 0").groupBy("root").agg(F.min(F.struct(F.col("doc").isNull().alias("no_id"), "doc", "row")).alias("first")).select("first.row")
    kept = kept.unionByName(rows.where("n = 0").select("row").distinct())
    return one_of_each_key(keyed.join(kept.withColumnRenamed("row", "_row"), "_row", "left_semi"), "_row").select(*docs.columns)
