"""Walks of runs coded stretch by stretch, against the same walks coded from all their nodes."""

import pathlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from carrierpath.operators import codec
from carrierpath.operators import runs as runs_
from carrierpath.plans import queries

from .test_runs import lines  # noqa: F401

RUNS = "path_id long, heads array<long>, firsts array<long>, lasts array<long>"


def walks(seed):
    """Runs over a spine of 300 segments, one of which no walk has: walks without a run, alternatives side by side, empty and single stretches, two contigs."""
    r = random.Random(seed)
    spine = [i * 7 % 301 for i in range(300)]
    spine[-1] = -9
    rows = [(0, [], [], []), (1, [None], [0], [298]), (2, [None, 400], [0, 299], [-1, 298])]
    for i in range(3, 60):
        cuts = sorted(r.sample(range(1, 298), r.choice([0, 1, 3, 12])))
        heads, firsts, lasts = [None], [0], []
        for c in cuts:
            lasts.append(c - 1)
            heads.append(400 + c)
            firsts.append(c + r.choice([0, 1, 1]))
        rows.append((i, heads + [None, 390], [*firsts, 299, 299], [*lasts, 298, 298, 298]))
    return spine, rows


@pytest.mark.parametrize("seed", [0, 1])
def test_lines_equal_all_nodes(spark, seed, monkeypatch):
    spine, rows = walks(seed)
    runs, line = spark.createDataFrame(rows, RUNS).coalesce(2).cache(), np.array(spine)
    nodes = codec.listed(runs, line).cache()
    assert nodes.agg(F.max(F.size("nodes"))).first()[0] > 200
    few = nodes.where("path_id % 4 <> 3")  # the others have steps that its book lacks
    for paths, alpha, stop in ((nodes, 1.0, True), (few, 1.0, True), (few, 0.0, False)):
        book = codec.fit(paths, alpha, stop).cache()
        columns = ["path_id", "n_symbols", "n_bits", "bits", "status"]
        got = lambda df, c=columns: sorted(map(repr, df.select(*c).collect()))
        want = got(codec.encode_by_row(nodes, book))
        assert got(codec.encode_by_row(runs, book, line)) == want
        assert any("unseen" in x for x in want) == (paths is few)
    assert got(codec.encode_by_row(runs, book.limit(0), line)) == got(codec.encode_by_row(nodes, book.limit(0)))


def test_only_steps_beside_alternatives_are_looked_up(spark, monkeypatch):
    spine = np.arange(10_000)
    nodes = spark.createDataFrame([(0, [*range(5_000), 10_000, *range(5_001, 10_000)]), (1, list(range(10_000)))], "path_id long, nodes array<long>")
    encoder, looked = codec.Encoder(codec._decoder(codec.fit(nodes)).value[0]), []
    line = codec.Line(encoder, spine)
    monkeypatch.setattr(encoder, "places", lambda ctx, sym: looked.append(len(ctx)) or codec.Encoder.places(encoder, ctx, sym))
    runs = spark.createDataFrame([(i, [None, 10_000], [0, 5_001], [4_999, 9_999]) for i in range(50)], RUNS).toArrow().combine_chunks().to_batches()[0]
    got = [x for _, _, *x in line.coded(runs)]
    assert sum(looked) == 50 * 4
    assert sum(int(width.sum()) for _, width, *_ in got) == 50 * len(encoder.bits(encoder.codes(np.array(nodes.first()["nodes"]))))


def test_stretches_listed_together_equal_steps(spark):
    """Whole streams, cut ones, and ones of another book, along a likeliest walk of several tiles."""
    r = random.Random(6)
    usual = [i * 7 % 1_400 for i in range(1_400)]
    walks_ = [[r.randint(1_400, 1_500) if r.random() < 0.01 else x for x in usual] for _ in range(20)] + [[], usual, usual[:5], usual[700:]]
    paths = spark.createDataFrame(list(enumerate(walks_)), "path_id long, nodes array<long>").coalesce(2).cache()
    rows = lambda df: sorted(map(repr, df.collect()))
    for escape in ("off", "reserved"):
        book = codec.fit(paths, escape=escape).cache()
        good = codec.encode_by_row(paths, book).cache()
        for encoded in (good, good.withColumn("n_bits", F.floor(F.col("n_bits") * 0.7)), codec.encode_by_row(paths, codec.fit(paths.where("path_id % 2 = 0")))):
            assert rows(codec.decode_alike(encoded, book)) == rows(codec.decode(encoded, book))


def test_decoded_files_do_not_hold_each_node_of_each_walk(spark, lines, tmp_path, monkeypatch):  # noqa: F811
    """200 walks of some 30,000 nodes: the query's result takes less than two bytes a row."""
    monkeypatch.setattr(runs_, "GROUPS", 1, raising=False)
    nodes = [*range(30_000)]
    paths = spark.createDataFrame([(i, nodes if i % 2 else [*nodes[: 100 * i], 40_000, *nodes[100 * i + 1 :]]) for i in range(200)], "path_id long, nodes array<long>").repartition(8).cache()
    book = codec.fit(paths).cache()
    monkeypatch.setattr(queries, "_encoded", lambda *_: (codec.encode_by_row(paths, book), book))
    at = str(tmp_path / "nodes")
    __spark_entry__.queries()["decode_walk_supplier"](spark, lines).write.parquet(at)
    assert spark.read.parquet(at).distinct().count() == 200 * 30_000
    assert sum(f.stat().st_size for f in pathlib.Path(at).glob("*.parquet")) < 2 * 200 * 30_000


def test_likeliest_walk_goes_on_where_only_the_end_is_as_short(spark):
    """Between two codes of one bit, the end's is there by smoothing alone."""
    book = codec.fit(spark.createDataFrame([(i, list(range(50))) for i in range(3)], "path_id long, nodes array<long>"))
    assert codec.Decoder(*codec._decoder(book).value).chain()[1].tolist() == [*range(50), -2]


def test_a_block_on_the_likeliest_walk_is_one_span(spark):
    paths = spark.createDataFrame([(i, list(range(100))) for i in range(3)], "path_id long, nodes array<long>").coalesce(1)
    book = codec.fit(paths).cache()
    decoder = codec.Decoder(*codec._decoder(book).value)
    blocks = codec.encode_blocks_by_row(paths, book, 32).where("path_id = 0").orderBy("block_no").collect()
    got = [[x.tolist() for x in decoder.spans(bytes(b["bits"]), b["n_bits"], b["entry_ctx"], b["n_symbols"]) if not isinstance(x, str)] for b in blocks]
    assert got == [[[*range(lo, min(lo + 32, 100)), *[-2] * (lo == 96)]] for lo in range(0, 100, 32)]
