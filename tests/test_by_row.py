"""Walks coded path by path from their runs, and decoding by spans."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from carrierpath.operators import codec, markov

from .test_runs import lines, moved  # noqa: F401


def test_by_row_equals_by_step(spark):
    rng = random.Random(3)
    paths = spark.createDataFrame([(i, [rng.randint(0, 6) for _ in range(rng.choice([0, 1, 9, 70]))]) for i in range(30)], "path_id long, nodes array<long>").coalesce(2).cache()
    for alpha, stop in ((0.0, False), (1.0, True)):
        book = codec.fit(paths.where("path_id % 5 > 0"), alpha, stop).cache()
        columns = ["path_id", "n_symbols", "n_bits", "bits", "status"]
        rows = lambda df, c=columns: sorted(map(repr, df.select(*c).collect()))
        assert rows(codec.encode(paths, book)) == rows(codec.encode_by_row(paths, book))
        book = codec.fit(paths, alpha, stop).cache()
        columns = ["path_id", "block_no", "entry_ctx", "first_seq", "n_symbols", "bit_offset", "n_bits", "bits"]
        assert rows(codec.encode_blocks(paths, book, 8), columns) == rows(codec.encode_blocks_by_row(paths, book, 8), columns)
    line = np.array([5, 6, 4])
    runs = spark.createDataFrame([(0, [None, 1, 2], [0, 2, 3], [1, 2, 2])], "path_id long, heads array<long>, firsts array<long>, lasts array<long>")
    assert [r["nodes"] for r in codec.listed(runs, line).collect()] == [[5, 6, 1, 4, 2]]


def test_spans_equal_steps(spark):
    """Whole streams, cut ones and wrong contexts, in books with and without an escape."""
    rng = random.Random(4)
    usual = list(range(40))
    walks = [[rng.randint(0, 50) if rng.random() < 0.05 else x for x in usual] for _ in range(25)] + [[]]
    paths = spark.createDataFrame(list(enumerate(walks)), "path_id long, nodes array<long>").coalesce(2).cache()
    for escape in ("off", "reserved", "literal"):
        book = codec.fit(paths, escape=escape).cache()
        packed, *rest = codec._decoder(book, escape, 6).value
        decoder = codec.Decoder(packed, *rest)
        for r in codec.encode(paths, book).collect():
            for n_bits, ctx, most in ((r["n_bits"], markov.START, 10**8), (r["n_bits"] // 2, markov.START, 10**8), (r["n_bits"], 7, 10**8), (r["n_bits"], markov.START, 11), (r["n_bits"], 999, 5)):
                want = [x for _, _, x, _ in decoder.steps(bytes(r["bits"]), n_bits, ctx, most)]
                got = [y for x in decoder.spans(bytes(r["bits"]), n_bits, ctx, most) for y in ([x] if isinstance(x, str) else x.tolist())]
                assert got == want


CODED = ["encode_walk_supplier", "decode_prefix", "decode_walk_supplier", "decode_blocks_walk_supplier", "incremental_touched", "ondisk_ratio"]


@pytest.mark.parametrize("name", CODED)
def test_no_coder_query_moves_all_nodes(spark, lines, name):  # noqa: F811
    out, rows = moved(spark, lambda: __spark_entry__.queries()[name](spark, lines).agg(F.count(F.lit(1))).collect())
    assert out[0][0] and rows < 15_000  # the walks have some 36,000 nodes
