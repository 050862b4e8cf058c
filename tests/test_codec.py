import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from carrierpath.operators import codec, diag, markov, normalize, prefix


def walks(spark, paths):
    return spark.createDataFrame(list(enumerate(paths)), "path_id long, nodes array<long>")


def best_cost(weights):
    """Least weighted depth over all full binary trees."""
    if len(weights) == 1:
        return 0
    return min(sum(p) + best_cost(tuple(sorted((*r, sum(p))))) for p in itertools.combinations(weights, 2) if (r := list(weights)) and all(r.remove(x) is None for x in p))


def test_huffman_is_optimal():
    rng = random.Random(2)
    for _ in range(60):
        w = sorted(rng.randint(1, 9) for _ in range(rng.randint(2, 6)))
        lens = prefix.huffman(w)
        assert sum(a * b for a, b in zip(w, lens, strict=True)) == best_cost(tuple(w))
        assert math.isclose(sum(2.0**-x for x in lens), 1)


def test_worked_coder(spark):
    paths = walks(spark, [[0, 1], [0, 1], [0, 2]])
    book = codec.fit(paths).cache()
    code = {(r["ctx"], r["sym"]): r["code"] for r in book.collect()}
    assert code[0, 1] == "0" and code[0, markov.STOP] == "10" and code[0, 2] == "11" and code[1, markov.STOP] == ""
    enc = codec.encode(paths, book)
    assert sorted(r["n_bits"] for r in enc.collect()) == [2, 2, 3]
    g = diag.global_(book, 1).first()
    assert (g["h_global"], g["l_global"], g["realized"], g["bound_violations"]) == (0.726999, 0.833333, 0.777778, 0) or round(g["h_global"], 4) == 0.7270
    one = codec.fit(paths, single_symbol="one_bit")
    assert sum(r["n_bits"] for r in codec.encode(paths, one).collect()) == 10
    assert codec.verify(paths, enc, book).count() == 0


@pytest.mark.parametrize("seed", [1, 2])
def test_random_walks_round_trip(spark, seed):
    rng = random.Random(seed)
    paths = walks(spark, [[rng.randint(0, 6) for _ in range(rng.choice([0, 1, 2, 9, 60]))] for _ in range(40)] + [[3, 3, 3]])
    for alpha, stop in ((0.0, False), (1.0, True), (0.5, True)):
        book = codec.fit(paths, alpha, stop).cache()
        enc = codec.encode(paths, book).cache()
        assert codec.verify(paths, enc, book).count() == 0
        for r in prefix.verify(book).collect():
            assert r["clashes"] == 0 and (r["kraft"] == 1 or r["symbols"] == 1)
        for r in diag.contexts(book).collect():
            assert r["h"] - 1e-9 <= r["l"] < r["h"] + 1
        g = diag.global_(book, 1).first()
        total = enc.agg(F.sum("n_bits"), F.sum("n_symbols")).first()
        assert abs(g["realized"] - total[0] / total[1]) < 1e-6
        if alpha == 0:
            assert abs(g["l_global"] - g["realized"]) < 1e-6
        blocks = codec.encode_blocks(paths, book, 7)
        want = paths.select("path_id", F.posexplode("nodes").alias("seq", "node"))
        got = codec.decode_blocks(blocks, book).select("path_id", "seq", "node")
        assert want.withColumn("seq", F.col("seq").cast("long")).exceptAll(got).count() == 0 and got.count() == want.count()


def test_errors_and_escape(spark):
    paths = walks(spark, [[0, 1, 2, 1], [2, 1, 0]])
    book = codec.fit(paths, escape="reserved").cache()
    unseen = walks(spark, [[1, 1]])
    assert codec.encode(unseen, book).first()["status"] == "unseen"
    with pytest.raises(Exception, match="unseen transition"):
        codec.encode(unseen, book, on_unseen="error").collect()
    literal = codec.encode(unseen, book, escape="literal", width=2)
    got = codec.decode(literal, book, escape="literal", width=2).orderBy("seq").collect()
    assert [r["node"] for r in got] == [1, 1] and {r["status"] for r in got} == {"ok"}
    assert codec.decode(literal, book).where("status = 'escape_unsupported'").count() == 1
    enc = codec.encode(paths, book)
    cut = enc.withColumn("n_bits", F.col("n_bits") - 1)
    assert codec.decode(cut, book).where("status = 'truncated'").count() == 2
    part = book.where("ctx <> 1")
    assert codec.decode(enc, part).where("status = 'invalid_prefix'").count() == 2


def test_signature_modes_share_codes(spark):
    paths = walks(spark, [[0, 1], [2, 3], [0, 1], [2, 3], [4, 0, 5]])
    sizes = {m: codec.fit(paths, cache=m).select("sig").distinct().count() for m in ("profile", "counts", "support", "off")}
    assert sizes["profile"] <= sizes["counts"] <= sizes["off"]
    lens = [{(r["ctx"], r["sym"]): r["len"] for r in codec.fit(paths, cache=m).collect()} for m in ("profile", "counts", "off")]
    assert lens[0] == lens[1] == lens[2]


def test_update_equals_refit(spark):
    a, b = walks(spark, [[0, 1], [1]]), walks(spark, [[0, 2, 1]])
    whole = markov.count(a.unionByName(b))
    assert markov.update(markov.count(a), markov.count(b)).exceptAll(whole).count() == 0


def test_index_and_edges(spark):
    labels = spark.createDataFrame([(x,) for x in ["b", "é", "a", "b", "z", "B"]], "label string")
    assert [tuple(r) for r in normalize.node_index(labels).orderBy("idx").collect()] == [("B", 0), ("a", 1), ("b", 2), ("z", 3), ("é", 4)]
    edges = spark.createDataFrame([(1, "a", "b"), (2, "b", "c"), (3, "x", "y")], "edge_id long, src string, dst string")
    paths = spark.createDataFrame([(0, [1, 2]), (1, [1, 3]), (2, [9])], "path_id long, edge_ids array<long>")
    got = {r["path_id"]: (r["labels"], r["ok"]) for r in normalize.expand_edges(paths, edges).collect()}
    assert got[0] == (["a", "b", "c"], True) and not got[1][1] and not got[2][1]


def test_save_and_load(spark, tmp_path):
    paths = walks(spark, [[0, 1, 1], [1]])
    book = codec.fit(paths)
    index = spark.createDataFrame([("a", 0), ("b", 1)], "label string, idx long")
    codec.save(str(tmp_path / "m"), codec.encode(paths, book), book, index)
    bits, again, _ = codec.load(spark, str(tmp_path / "m"))
    assert codec.verify(paths, bits, again).count() == 0 and codec.bytes_on_disk(spark, str(tmp_path / "m")) > 0


def test_blocks_decode_with_the_codes_of_their_contexts_alone(spark, monkeypatch):
    rng = random.Random(8)
    paths = walks(spark, [[rng.choice([1, 1, 1, 2, 3, 40]) for _ in range(rng.choice([0, 1, 5, 70]))] for _ in range(25)])
    book = codec.fit(paths).checkpoint()
    monkeypatch.setattr(codec, "BROADCAST_ROWS", 3)
    blocks = codec.encode_blocks(paths, book, 8).checkpoint()
    with pytest.raises(ValueError):
        codec.decode_blocks(blocks, book)
    got = {(r["path_id"], r["seq"]): (r["node"], r["status"]) for r in codec.decode_blocks_joined(blocks, codec.block_contexts(paths, 8), book).collect()}
    want = {(r["path_id"], i): (x, "ok") for r in paths.collect() for i, x in enumerate(r["nodes"])}
    assert got == want
    monkeypatch.setattr(codec, "ENCODER_ROWS", 0)  # the same bits when the codes are joined by a shuffle
    assert {tuple(r) for r in codec.encode_blocks(paths, book, 8).collect()} == {tuple(r) for r in blocks.collect()}


def test_refit_equals_a_new_fit(spark):
    paths = spark.createDataFrame([(1, [0, 1, 2]), (2, [0, 1, 1]), (3, [3]), (4, [0, 2, 4])], "path_id long, nodes array<long>")
    book = codec.fit(paths.where("path_id < 4"))
    got = codec.refit(book, markov.count(paths.where("path_id = 4")))
    key = lambda b: sorted((r["ctx"], r["sym"], r["n"], r["code"]) for r in b.collect())
    assert key(got) == key(codec.fit(paths))
    assert key(codec.refit(book, markov.count(paths.limit(0)))) == key(book)
