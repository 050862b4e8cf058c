"""Nodes of walks as files hold them: equal stretches of many walks stand together."""

import pathlib

from pyspark.sql import functions as F

from carrierpath.operators import runs


def test_files_do_not_hold_each_node_of_each_walk(spark, tmp_path, monkeypatch):
    """200 walks over 40,000 segments of two contigs, of which some have an alternative, each at its own place."""
    monkeypatch.setattr(runs, "GROUPS", 1, raising=False)
    begins = spark.range(200).select(F.col("id").alias("path_id"), F.explode(F.array(F.lit(0), F.lit(1))).alias("_c"))
    alt = F.when((F.col("_c") == 1) & (F.col("path_id") % 3 == 0), F.col("path_id") * 90 + 20_010)  # its alternative replaces this segment
    own = begins.select("path_id", F.concat(F.lit("c"), F.col("_c").cast("string")).alias("contig"), (F.col("_c") * 20_000).alias("lo"), alt.alias("alt"))
    none = F.lit(None)
    straight = own.select("path_id", "contig", none.cast("long").alias("at"), none.cast("string").alias("node"), none.cast("long").alias("allele_id"), F.col("lo").cast("long").alias("first"), F.coalesce(F.col("alt") - 1, F.col("lo") + 19_999).cast("long").alias("last"))
    bent = own.where("alt is not null").select("path_id", "contig", F.col("alt").alias("at"), F.concat(F.lit("A"), F.col("alt").cast("string")).alias("node"), F.col("alt").alias("allele_id"), (F.col("alt") + 1).alias("first"), (F.col("lo") + 19_999).cast("long").alias("last"))
    at = str(tmp_path / "nodes")
    runs.numbered(straight.unionByName(bent)).write.parquet(at)
    got = spark.read.parquet(at)
    n = got.count()
    assert n == 200 * 40_000 and got.select("path_id", "seq").distinct().count() == n
    assert got.where("node <> concat(if(node like 'A%', 'A', 'R'), seq)").count() == 0 and got.where("node like 'A%'").count() == 67
    assert sum(f.stat().st_size for f in pathlib.Path(at).glob("*.parquet")) < 2 * n  # two bytes for each node


def test_two_contigs_keep_their_nodes_apart(spark):
    """A tile that two contigs share, and an alternative before all segments."""
    own = spark.createDataFrame([(i, c, at, node, None, a, z) for i in range(40) for c, at, node, a, z in (("c0", None, None, 0, -1), ("c0", -100, "A7", 0, 299), ("c1", None, None, 300, 599))], "path_id long, contig string, at long, node string, allele_id long, first long, last long")
    got = sorted(runs.numbered(own).where("path_id = 39").select("seq", "contig", "node").collect())
    assert [tuple(r) for r in got] == [(0, "c0", "A7"), *((i + 1, f"c{i // 300}", f"R{i}") for i in range(600))]
