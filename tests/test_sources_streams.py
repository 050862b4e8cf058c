import datetime

from pyspark.sql import functions as F

from carrierpath.sources import tables
from carrierpath.streaming import streams


def test_genotype_text(spark, tmp_path):
    lines = ["##x", "#CHROM", "1\t100\trs1\tA\tC,G\t.\tPASS\tAC=1\tGT:DP\t0|1:3\t2|.:4", "1\t200\tsv1\tA\t<DEL>\t.\tPASS\tEND=300;SVTYPE=DEL\tGT\t1|1\t0|0"]
    (tmp_path / "g.txt").write_text("\n".join(lines) + "\n")
    calls = tables.read_genotypes(spark, str(tmp_path / "g.txt")).collect()
    got = {(r["site_id"], r["sample_no"], r["phase"], r["allele"], r["sv_type"]) for r in calls if r["allele"] > 0}
    assert got == {("rs1", 0, 1, 1, None), ("rs1", 1, 0, 2, None), ("sv1", 0, 0, 1, "DEL"), ("sv1", 0, 1, 1, "DEL")}
    assert len(calls) == 7


def test_replay_equals_batch_and_late_rows_drop(spark, tmp_path):
    base = datetime.datetime(2024, 1, 1)
    rows = [(i, base + datetime.timedelta(hours=i), i % 3, "ab"[i % 2], 0.0, '{"k": 1}') for i in range(60)]
    events = spark.createDataFrame(rows, streams.EVENTS)
    for part, name in ((rows[:30], "0"), (rows[30:], "1"), ([(99, base, 0, "a", 0.0, '{"k": 1}')], "2")):
        spark.createDataFrame(part, streams.EVENTS).coalesce(1).write.parquet(str(tmp_path / "in" / name))
    stream = streams.window_carriers(spark.readStream.schema(streams.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in")).withWatermark("ts", "1 hour"))
    run = stream.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "log")).outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    got = {(r["start"], r["allele_id"]): r["k"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    want = {(r["start"], r["allele_id"]): r["k"] for r in streams.window_carriers(events).collect()}
    assert got and all(want[k] == v for k, v in got.items())


def test_model_refresh_is_idempotent(spark, tmp_path):
    spark.createDataFrame([(1, -1, 2), (1, 5, 1)], "ctx long, sym long, n long").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("ctx long, sym long, n long").parquet(str(tmp_path / "in"))
    for _ in range(2):
        streams.refresh_model(stream, str(tmp_path / "model"), str(tmp_path / "log")).awaitTermination()
    got = {(r["ctx"], r["sym"]): r["n"] for r in streams.model(spark, str(tmp_path / "model")).select("ctx", "sym", F.col("n")).collect()}
    assert got == {(1, -1): 2, (1, 5): 1}
