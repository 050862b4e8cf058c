"""Streaming forms: transition counts with one state cell per user, session walks, windowed carriers, model refresh."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import markov

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def replay(spark: SparkSession, folder: str, late: str = "1 hour", files: int = 1) -> DataFrame:
    """A stream of the event files of a folder, with a watermark on the event time."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(folder).withWatermark("ts", late)


def transitions(stream: DataFrame) -> DataFrame:
    """(user_id, ctx, sym, n) of each micro-batch: steps between consecutive events of a user; the state is the user's last symbol.

    A user's events must come in order across batches; within one they are sorted here, by time and then by id.
    """

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else "START"
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        made: dict[tuple[str, str], int] = {}
        for sym in rows["event_type"]:
            made[last, sym] = made.get((last, sym), 0) + 1
            last = sym
        state.update((last,))
        yield pd.DataFrame([(key[0], a, b, n) for (a, b), n in made.items()], columns=["user_id", "ctx", "sym", "n"])

    own = stream.select("user_id", "ts", "event_id", "event_type")
    return own.groupBy("user_id").applyInPandasWithState(step, "user_id long, ctx string, sym string, n long", "last string", "append", GroupStateTimeout.NoTimeout)


def window_users(stream: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """(w, allele_id, user_id), each once, in tumbling or sliding windows: the state is one row per carrier, dealt by all three, so a frequent allele fills no single row."""
    allele = F.concat("event_type", F.lit(":"), F.get_json_object("props", "$.k"))
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.select(w.alias("w"), allele.alias("allele_id"), "user_id").dropDuplicates(["w", "allele_id", "user_id"])


def window_carriers(stream: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, allele_id, k): distinct carriers of each allele in tumbling or sliding windows; a stream gives a window when it is past the watermark."""
    return counted(window_users(stream, width, slide))


def counted(users: DataFrame) -> DataFrame:
    return users.groupBy("w", "allele_id").agg(F.count(F.lit(1)).alias("k")).select(F.col("w.start").alias("start"), "allele_id", "k")


def session_walks(stream: DataFrame, gap: str = "1 hour") -> DataFrame:
    """(user_id, start, labels): a gap closes a walk."""
    own = stream.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("x"))
    return own.select("user_id", F.col("s.start").alias("start"), F.transform("x", lambda e: e["event_type"]).alias("labels"))


def ended(walks: DataFrame, index: DataFrame) -> DataFrame:
    """(path_id, user_id, start, nodes) of closed sessions, of a micro-batch, by a label index; a label that the index lacks becomes node -4, which no code has. The coder ends each walk by the end symbol."""
    each = walks.select(F.struct("user_id", "start").alias("path_id"), F.posexplode("labels").alias("at", "label")).join(index, "label", "left")
    own = each.groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("at", F.coalesce("idx", F.lit(-4).cast("long")).alias("idx")))).alias("s"))
    return own.select("path_id", F.transform("s", lambda x: x["idx"]).alias("nodes"))


def late_rows(run: StreamingQuery) -> int:
    """Rows that the operators of a finished run dropped because they were behind the watermark, over the progress that the session keeps (100 batches unless set otherwise)."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in run.recentProgress for op in p["stateOperators"])


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def refresh_model(stream: DataFrame, path: str, checkpoint: str):
    """Adds each micro-batch of (ctx, sym, n) to the counts under ``path``; a batch that comes again replaces itself."""

    def add(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("ctx", "sym").agg(F.sum("n").alias("n")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def model(spark: SparkSession, path: str) -> DataFrame:
    counts = spark.read.parquet(path)
    return markov.update(counts.where("false"), counts)
