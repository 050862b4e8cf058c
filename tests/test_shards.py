"""Coding by shards against the coder of single steps."""

import random

import numpy as np
import pyarrow as pa
import pytest

import __spark_entry__
from carrierpath.operators import codec, markov, prefix, shards

from .test_runs import lines, moved  # noqa: F401


def test_two_queues_equal_the_heap():
    r = random.Random(1)
    for _ in range(3000):
        w = sorted(float(r.randint(1, r.choice([2, 5, 40, 1000]))) for _ in range(r.randint(2, r.choice([4, 12, 60]))))
        assert shards.huffman(w) == prefix.huffman(w)


@pytest.mark.parametrize("name", ["decode_words", "decode_blocks_words"])
def test_words_need_no_codebook_of_a_broadcast_size(spark, tmp_path, monkeypatch, name):
    texts = {0: "a b  a é a", 1: "", 2: None, 3: " ", 4: "b " * 70 + "Z", 9: "\ta\n b a"}
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts.items()], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    monkeypatch.setattr(codec, "BROADCAST_ROWS", 3)
    words = {i: [w for w in (t or "").split(" ") if w] for i, t in texts.items()}
    number = {w: i for i, w in enumerate(sorted({w for own in words.values() for w in own}))}
    got = __spark_entry__.queries()[name](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [(i, at, number[w]) for i, own in words.items() for at, w in enumerate(own)]


def test_shards_equal_the_coder_of_steps(spark, monkeypatch):
    r = random.Random(5)
    names = [r.choice("abé") * r.randint(1, 4) + str(r.randint(0, 60)) for _ in range(200)]
    walks = [(3 * i, [r.choice(names[: r.choice([3, 30, 200])]) for _ in range(r.choice([0, 1, 2, 40, 200]))]) for i in range(40)]
    number = {w: i for i, w in enumerate(sorted({w for _, own in walks for w in own}))}
    paths = spark.createDataFrame([(i, [number[w] for w in own]) for i, own in walks if own], "path_id long, nodes array<long>")
    book, build = codec.fit(paths).cache(), shards.build
    monkeypatch.setattr(shards, "build", lambda x: build(x, 500))
    monkeypatch.setattr(shards, "PAIRS", 400)
    monkeypatch.setattr(shards, "LABELS", 20)
    for block, want in ((None, codec.encode(paths, book)), (8, codec.encode_blocks(paths, book, 8))):
        made = shards.encode(spark.createDataFrame(walks, "path_id long, labels array<string>").repartition(3), block).cache()
        columns = ["path_id", "n_symbols", "n_bits", "bits"] + ["block_no", "entry_ctx", "first_seq"] * (block is not None)
        rows = lambda df, c=columns: sorted(map(repr, df.select(*c).collect()))
        assert rows(made.where("book is null")) == rows(want) and made.where("book is not null").count() > 3
        got = sorted((r["path_id"], r["seq"], r["node"], r["status"]) for r in shards.decode(made).collect())
        assert got == [(i, at, number[w], "ok") for i, own in walks for at, w in enumerate(own)]


def test_joined_blocks_move_no_walks(spark, lines):  # noqa: F811
    query = __spark_entry__.queries()
    got, rows = moved(spark, lambda: query["decode_blocks_joined_walk_supplier"](spark, lines).collect())
    assert got and rows < 15_000  # the walks have some 36,000 nodes
    assert sorted(got) == sorted(query["decode_blocks_walk_supplier"](spark, lines).collect())


def test_blocks_of_a_shard_share_their_codes(spark):
    """A common context met its whole alphabet once for each block: 400 times 200 codes here."""
    paths = spark.createDataFrame([(i, [0, 1 + i % 200, 0, 1 + (7 * i) % 200]) for i in range(400)], "path_id long, nodes array<long>").coalesce(2).cache()
    book = codec.fit(paths).checkpoint()
    blocks = codec.encode_blocks(paths, book, 4).checkpoint()
    got, rows = moved(spark, lambda: codec.decode_blocks_joined(blocks, codec.block_contexts(paths, 4), book, 500).collect())
    assert sorted(map(tuple, got)) == sorted((r["path_id"], i, x, "ok") for r in paths.collect() for i, x in enumerate(r["nodes"])) and rows < 20_000


@pytest.mark.parametrize("few", [0, 1000])
def test_streams_together_equal_streams_alone(spark, monkeypatch, few):
    """Whole streams, cut ones, wrong contexts and books without some codes."""
    monkeypatch.setattr(shards, "FEW", few)
    r = random.Random(6)
    paths = spark.createDataFrame([(i, [r.choice([1, 1, 1, 2, 3, r.randint(4, 40)]) for _ in range(r.choice([0, 1, 9, 60]))]) for i in range(30)], "path_id long, nodes array<long>").coalesce(2)
    book = codec.fit(paths).cache()
    streams = [(b"" if x["bits"] is None else bytes(x["bits"]), n, ctx, most) for x in codec.encode(paths, book).collect() for n, ctx, most in (
        (x["n_bits"], markov.START, x["n_symbols"]), (x["n_bits"] // 2, markov.START, 99), (x["n_bits"], 2, 99), (x["n_bits"], markov.START, 4), (x["n_bits"], 999, 5))]
    packed = codec._decoder(book).value[0]
    packed = [x.astype(np.int64) for x in packed]
    for own, wide in ((packed, 0), ([x[np.arange(len(x)) % 7 > 0] for x in packed], 0), (packed, 1)):
        together = shards.Together(own)
        together.alone = codec.Decoder(own) if wide else together.alone
        stream, step, node, status = together.decode(*(np.array([s[i] for s in streams]) for i in (2, 3, 1)), pa.array([s[0] for s in streams], pa.binary()))
        alone = codec.Decoder(own)
        for i, (data, n_bits, ctx, most) in enumerate(streams):
            want = [x for _, _, x, _ in alone.steps(data, n_bits, ctx, most) if x != "runaway"]
            mine = stream == i
            assert step[mine].tolist() == list(range(len(want)))
            assert [["ok", "invalid_prefix", "truncated"][z] if z else x for x, z in zip(node[mine].tolist(), status[mine].tolist(), strict=True)] == want


def test_values_are_joined_like_text():
    r = random.Random(8)
    size = np.array([r.choice([0, 1, 3, 12, 31, 52]) for _ in range(3000)])
    value = np.array([r.getrandbits(int(n)) if n else 0 for n in size], dtype=np.int64)
    text = "".join(f"{v:0{n}b}" if n else "" for v, n in zip(value.tolist(), size.tolist(), strict=True))
    width = -(-len(text) // 8) * 8
    assert shards.joined(value, size, np.cumsum(size) - size, width) == int(text.ljust(width, "0"), 2).to_bytes(width // 8, "big")
    assert shards.joined(value[size == 0], size[size == 0], size[size == 0], 0) == b""


def test_a_shard_holds_few_arrays_of_its_steps():
    """Numbering the steps of a shard held ten arrays of eight bytes a step, and workers kept what was freed."""
    import tracemalloc

    n, r = 400_000, np.random.default_rng(3)
    local = r.integers(0, 5000, n) * (r.random(n) < 0.02)  # few distinct transitions
    rows = [(0, -1, n, shards.pack(np.arange(40)), shards.pack(np.full(40, n // 40)), shards.pack(local)), (1, 0, 7, shards.pack(np.diff(np.arange(5000), prepend=0)), shards.pack(np.arange(5000)), None)]
    tracemalloc.start()
    own = shards.Shard(rows)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 8 * 6 * n and own.steps.nbytes <= 4 * (n + 40)
    walks = [[x + 7 for x in w.tolist()] for w in np.split(local, 40)]
    want = {(c, s) for w in walks for c, s in zip([markov.START, *w], [*w, markov.STOP], strict=True)}
    assert list(zip(own.ctx.tolist(), own.sym.tolist(), strict=True)) == sorted(want) and own.n.sum() == n + 40
