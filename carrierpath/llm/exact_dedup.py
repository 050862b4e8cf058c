"""Exact duplicate removal with a heavy-hitter split.

A text may have copies in a third of all rows, so one shuffle by digest would
send that third to one task. Three steps avoid it:

1. Misra-Gries style frequent-items sketches (mergeable, of fixed size, one for each
   shard of the digest space) over all digests propose candidates;
2. the candidates are verified exactly by a partially aggregated count, so a false
   proposal costs nothing and a missed one only moves to step 3;
3. the verified winners, at most ``max_heavy`` of them, are broadcast and settle
   their rows on the map side; the rows of all other digests are shuffled as usual.

The split changes where a row is settled, never how. Null texts count as empty;
ties cannot occur as the row with the smallest id stays; repeated rows (same id and
text) each get a row in the groups, all of them marked if their id is the kept one, but
:func:`drop_duplicates` leaves one row of each group, also of a group without ids.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, cut, text_of

#: A digest is worth broadcasting from this many copies on.
MIN_HEAVY = 64
#: Most digests that are broadcast; with id and count about 50 bytes each.
MAX_HEAVY = 2048
#: Shards of the digest space, each with a sketch of its own, and counters of a sketch.
#: A digest with over 2/COUNTERS of its shard's rows is always proposed.
SHARDS, COUNTERS = 64, 256


def normalised(text: Column) -> Column:
    return F.regexp_replace(text, SPACES, " ")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row (id, digest) per row: sha-256 of the text with white space normalised."""
    return docs.select(
        F.col(id_col).alias("doc_id"),
        F.unhex(F.sha2(normalised(text_of(text_col)).cast("binary"), 256)).alias("digest"),
    )


def heavy_digests(
    keyed: DataFrame, min_heavy: int = MIN_HEAVY, max_heavy: int = MAX_HEAVY, shards: int = SHARDS, counters: int = COUNTERS
) -> DataFrame:
    """Verified frequent digests (digest, keep_id, group_size), at most ``max_heavy`` rows."""
    short = F.xxhash64("digest")
    found = (
        keyed.select(short.alias("h"))
        .groupBy(F.pmod("h", F.lit(shards)).alias("shard"))
        .agg(F.expr(f"approx_top_k(h, {max(1, max_heavy // shards)}, {counters})").alias("top"))
    )
    proposed = found.select(F.explode("top").alias("t")).where(F.col("t.count") >= min_heavy).select(
        F.col("t.item").alias("h")
    )
    return (
        keyed.withColumn("h", short)
        .join(F.broadcast(proposed), "h", "left_semi")
        .groupBy("digest")
        .agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .where(F.col("group_size") >= min_heavy)
    )


def duplicate_groups(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    min_heavy: int = MIN_HEAVY,
    max_heavy: int = MAX_HEAVY,
) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row per row of ``docs``."""
    keyed = cut(digests(docs, id_col, text_col))
    heavy = cut(heavy_digests(keyed, min_heavy, max_heavy))
    ready = F.broadcast(heavy)  # at most max_heavy rows
    frequent = keyed.join(ready, "digest").select("doc_id", "digest", "keep_id", "group_size")
    few = keyed.join(ready.select("digest"), "digest", "left_anti")
    # Counted with partial sums and joined back, so that a frequent digest that the sketches missed is no single task's.
    groups = few.groupBy("digest").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    rest = few.join(groups, "digest").select("doc_id", "digest", "keep_id", "group_size")
    return frequent.unionByName(rest).select(
        "doc_id",
        "keep_id",
        F.col("group_size").cast("long").alias("group_size"),
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def drop_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_heavy: int = MIN_HEAVY, max_heavy: int = MAX_HEAVY) -> DataFrame:
    """One row of ``docs`` for each different text, with all its columns: one with the least id, and one without an id only if none has one."""
    keyed = cut(digests(docs, id_col, text_col))
    heavy = cut(heavy_digests(keyed, min_heavy, max_heavy))
    own = F.unhex(F.sha2(normalised(text_of(text_col)).cast("binary"), 256))
    rows = docs.select(F.struct(*docs.columns).alias("_own"), own.alias("_digest"), F.col(id_col).alias("_id"))
    # Of a frequent text only rows with the kept id are shuffled, and of these one from each task.
    rows = rows.join(F.broadcast(heavy.select(F.col("digest").alias("_digest"), "keep_id", F.lit(True).alias("_heavy"))), "_digest", "left")
    rows = rows.where(F.col("_heavy").isNull() | F.col("_id").eqNullSafe(F.col("keep_id")))
    first = F.struct(F.col("_id").isNull(), "_id", F.xxhash64("_own"))
    return rows.groupBy("_digest").agg(F.min_by("_own", first).alias("_own")).select("_own.*")
