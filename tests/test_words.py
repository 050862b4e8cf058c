import math
import random
from collections import Counter

import __spark_entry__
from carrierpath.operators import codec, markov, prefix


def test_coder_queries_read_all_words(spark, tmp_path):
    rng = random.Random(4)
    texts = {i: " ".join(rng.choice(["a", "b", "cc", "é", "Zz"]) for _ in range(rng.choice([0, 1, 5, 40, 900, 3000]))) for i in range(30)}
    assert any(len(t) > 400 for t in texts.values()) and any(0 < len(t) <= 400 for t in texts.values())
    spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    run = lambda name: __spark_entry__.queries()[name](spark, str(tmp_path)).collect()
    number = {w: i for i, w in enumerate(sorted({w for t in texts.values() for w in t.split()}))}
    nodes = {i: [number[w] for w in t.split()] for i, t in texts.items() if t}
    counts = Counter(p for own in nodes.values() for p in zip([markov.START, *own], [*own, markov.STOP], strict=True))
    weight = {}
    for (ctx, sym), n in counts.items():
        weight.setdefault(ctx, {markov.STOP: 1.0})[sym] = n + 1.0
    length = {}
    for ctx, own in weight.items():
        ranked = sorted((w, sym) for sym, w in own.items())
        length.update({(ctx, sym): k for (_, sym), k in zip(ranked, prefix.huffman([w for w, _ in ranked]), strict=True)})
    assert {(r["ctx"], r["sym"]): r["len"] for r in run("code_lengths_words")} == length
    bits = {i: sum(length[p] for p in zip([markov.START, *own], [*own, markov.STOP], strict=True)) for i, own in nodes.items()}
    assert {r["path_id"]: (r["n_symbols"], r["n_bits"], r["status"]) for r in run("encode_words")} == {i: (len(nodes[i]) + 1, n, "ok") for i, n in bits.items()}
    steps = sorted((i, at, x) for i, own in nodes.items() for at, x in enumerate(own))
    for name in ("decode_words", "decode_blocks_words"):
        assert sorted((r["path_id"], r["seq"], r["node"]) for r in run(name)) == steps
    for r in run("context_diagnostics_words"):
        own = weight[r["ctx"]]
        total = sum(own.values())
        assert r["events"] == sum(n for (c, _), n in counts.items() if c == r["ctx"]) and r["alphabet"] == len(own)
        assert abs(r["h"] + sum(w / total * math.log2(w / total) for w in own.values())) < 1e-5
    assert {r["ctx"]: (r["symbols"], r["kraft"]) for r in run("kraft_check_words")} == {c: (len(own), 1.0) for c, own in weight.items()}
    assert {r["min_events"]: r["contexts_kept"] for r in run("min_events_sweep_words")} == {m: sum(sum(n for (c, _), n in counts.items() if c == x) >= m for x in weight) for m in (1, 10, 100)}
    assert sum(counts.values()) == run("global_diagnostics_words")[0]["symbols"]


def test_decoder_forgets_and_unpacks_again(spark, monkeypatch):
    rng = random.Random(9)
    paths = spark.createDataFrame([(i, [rng.randint(0, 40) for _ in range(200)]) for i in range(8)], "path_id long, nodes array<long>")
    book = codec.fit(paths).cache()
    packed, escape, width = codec._decoder(book, "off", 0).value
    monkeypatch.setattr(codec, "UNPACKED_ROWS", 5)
    decoder = codec.Decoder(packed, escape, width)
    nodes = {r["path_id"]: r["nodes"] for r in paths.collect()}
    for r in codec.encode(paths, book).collect():
        assert [sym for _, _, sym, _ in decoder.steps(r["bits"], r["n_bits"])] == [*nodes[r["path_id"]], markov.STOP]
    assert len(decoder.codes) < 42


def test_short_documents_are_read_once(spark):
    """The index and the paths each went through the table of all documents again."""
    from carrierpath.sources import fixtures

    own = fixtures.word_paths(spark, "/root/testdata/sf0.001", 400)
    assert "parquet" not in own._jdf.queryExecution().toString().lower()
    assert own.count() == fixtures.word_arrays(spark, "/root/testdata/sf0.001", 400).selectExpr("sum(size(labels))").first()[0]
