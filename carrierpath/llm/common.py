"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the contracts: space and the controls from tab to carriage return.
SPACES = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names; only a session without one (tests, a single machine) gets its own."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="carrierpath-checkpoint-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """``df`` computed once and kept in the shared checkpoint folder, with its lineage cut."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def sized(df: DataFrame, most: int) -> DataFrame:
    """A table that was cut, marked for broadcast if it has at most ``most`` rows, for a shuffled join if not."""
    return F.broadcast(df) if df.count() <= most else df


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_of(name: str = "text") -> Column:
    """The text, null counting as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def row_key(id_col: Column, text: Column) -> Column:
    """A digest of id and text, never null: null ids differ from all others, null texts count as empty."""
    own = F.coalesce(F.concat(F.lit("i"), id_col.cast("string")), F.lit("n"))
    return F.sha2(F.concat(F.sha2(own.cast("binary"), 256), F.coalesce(text.cast("string"), F.lit(""))).cast("binary"), 256)


def one_of_each_key(rows: DataFrame, key: str) -> DataFrame:
    """One row of each key, which is a column of ``rows``: always the same one, whatever the order of the rows."""
    cols = [c for c in rows.columns if c != key]
    own = rows.groupBy(key).agg(F.min_by(F.struct(*cols), F.xxhash64(*cols)).alias("_own"))
    return own.select(key, "_own.*")


def word_count(text: Column) -> Column:
    """Number of runs of anything but white space."""
    bare = F.regexp_replace(text, r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")
    return F.when(bare == "", F.lit(0)).otherwise(
        F.size(F.split(bare, SPACES))
    ).cast("long")


def uniform(*parts: Column) -> Column:
    """A number in (0, 1) that depends on nothing but the parts: 52 bits of their md5."""
    key = F.concat_ws("|", *[F.coalesce(p.cast("string"), F.lit("\u0000")) for p in parts])
    bits = F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("long")
    return (bits.cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))
