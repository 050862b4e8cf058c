import hashlib
import random
import zlib

import public_tokenizers
import tiktoken

from carrierpath.llm import byte_bpe, chat_format, html_extract, toxicity

TURNS = "conv_id long, turn long, role string, text string, formatted string"


def test_chat_windows_read_back(spark):
    rng = random.Random(3)
    pieces = ["</s>", "[INST]", "\\", "<s>", "[TURN]", "ok ", "é", "<<SYS>>", "[/TURN]", "\n", "x y z "]
    convs = {}
    for c in range(25):
        turns = [("system", "be " * rng.randint(0, 3))] if c % 2 else []
        turns += [(rng.choice(["user", "assistant", "tool", None, "a[AS]b"]), "".join(rng.choice(pieces) for _ in range(rng.randint(0, 30)))) for _ in range(rng.randint(1, 12))]
        convs[c] = turns
    convs[90] = [("user", "w " * 30_000), ("assistant", None), ("assistant", "a"), ("assistant", "a")]
    rows = [(c, i, r, t, "x") for c, ts in convs.items() for i, (r, t) in enumerate(ts)]
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, TURNS)
    for budget, history in ((20, 2), (10_000, 1), (1, 0)):
        made = chat_format.format_chats(df, budget, history)
        got = {r["conv_id"]: r for r in chat_format.read_back(made).collect()}
        assert set(got) == set(convs)
        for c, ts in convs.items():
            said = "".join(f"{'' if r is None else r}\n{t or ''}\n" for r, t in ts)
            loss = "".join(t or "" for r, t in ts if r == "assistant")
            r = got[c]
            assert (r["n_turns"], r["turns_sha256"]) == (len(ts), hashlib.sha256(said.encode()).hexdigest())
            assert (r["loss_chars"], r["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
        for w in made.collect():
            assert w["n_tokens"] <= budget or w["n_new"] == 1 or w["n_system"]
            assert w["n_history"] <= history
    assert chat_format.read_back(chat_format.format_chats(df.where("false"))).count() == 0


def test_bpe_equals_tiktoken_and_decodes(spark):
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    ranks = byte_bpe.read_ranks(path)
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    own = byte_bpe.Codec(byte_bpe.tokenizer_json(ranks, public_tokenizers.PATTERN))
    rng = random.Random(1)
    parts = ["a", " ", "  ", "\n", " \n", "\t", "-", "=", "é", "的", "😀", "12", "'s", " the", "​", "\r\n", "ß", "\x00", "\xa0", "　", " x", "<|endoftext|>"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 60))) for _ in range(1500)] + ["", "x" * 100_000]
    for text, ids in zip(texts, own.encode(texts), strict=True):
        assert ids == reference.encode_ordinary(text)
        assert own.decode_bytes(ids) == text.encode()
    assert own.offsets("é 😀")[-1][1] == len("é 😀".encode())
    docs = spark.createDataFrame([(i, t, 0) for i, t in enumerate(texts[:50])] + [(99, None, 0), (99, None, 0)], "doc_id long, text string, n_tokens int")
    got = {r["doc_id"]: r for r in byte_bpe.round_trip(docs, path, public_tokenizers.PATTERN).collect()}
    for i, t in enumerate(texts[:50]):
        ids = reference.encode_ordinary(t)
        assert got[i]["ids_sha256"] == hashlib.sha256(b"".join(x.to_bytes(4, "little") for x in ids)).hexdigest() and got[i]["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest()
    assert got[99]["n_tokens"] == 0
    encoded = byte_bpe.encode(docs.limit(5), path, public_tokenizers.PATTERN)
    assert {r["doc_id"]: r["text"] for r in byte_bpe.decode(encoded, path, public_tokenizers.PATTERN).collect()} == {r["doc_id"]: r["text"] for r in docs.limit(5).collect()}


PAGE = """<!DOCTYPE html><html><head><title>no</title><style>p{x}</style><script>var t="</p>";</script></head><body>
<nav><ul><li><a href="/a">menu</a></li></ul></nav><div class="ad">buy &amp; save</div><article><h1>Head &lt;1&gt;</h1><p>First <b>bo</b>ld<br>line.
<p>Second &eacute; para.</p><aside><p>side note</p></aside><div class="comments"><div class="comment"><p>reader says</p></div></div></article><footer>&copy; me</footer></body></html>"""


def test_html_pages(spark):
    field = html_extract.default_field()
    wrong = total = 0
    for page, labels in html_extract.labelled_pages(150, seed=123):
        got = field.decode(html_extract.features(html_extract.leaf_blocks(page)))
        wrong += sum(a != b for a, b in zip(got, labels, strict=True))
        total += len(labels)
    assert wrong <= 0.01 * total
    rows = [(1, "u", PAGE), (2, "u", None), (3, None, ""), (4, "u", "<p"), (5, "u", PAGE[:400]), (1, "u", PAGE)]
    got = [(r["page_id"], r["text"], r["n_chars"]) for r in html_extract.extract(spark.createDataFrame([(*r, "t") for r in rows], "page_id long, url string, html string, text string")).collect()]
    want = "Head <1> First bold line. Second é para."
    assert got.count((1, want, len(want))) == 2 and {(2, "", 0), (3, "", 0), (4, "", 0)} <= set(got)


def brute_segments(scores):
    best, total = None, [0.0]
    for s in scores:
        total.append(total[-1] + s)
    for i in range(len(scores)):
        for j in range(i + 1, len(scores) + 1):
            if total[j] - total[i] > 1e-12 and (best is None or total[j] - total[i] > best[0] + 1e-9):
                best = (total[j] - total[i], i, j)
    if not best:
        return []
    _, i, j = best
    return brute_segments(scores[:i]) + [(i, j - 1)] + [(a + j, b + j) for a, b in brute_segments(scores[j:])]


def test_maximal_segments():
    rng = random.Random(4)
    for _ in range(300):
        scores = [rng.choice([0.4, 1.3, 3.0]) + rng.random() if rng.random() < 0.25 else -0.7 for _ in range(rng.randint(1, 35))]
        got = toxicity.segments([(i, s) for i, s in enumerate(scores) if s > 0], -0.7)
        assert [(a, b) for a, b, _ in got] == brute_segments(scores)


def test_toxicity_scores(spark):
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("th on er an re".split()) for _ in range(3))
    rows, labels = [], []
    for i in range(1200):
        bad = i % 8 == 0
        t = [word() for _ in range(rng.randint(20, 60))]
        for _ in range(3 * bad):
            t[rng.randrange(len(t))] = rng.choice(["vilefool", "vilerat", "scumlord", "blockhead"])
        rows.append((i, " ".join(t), "en", 7))
        if i % 2 == 0:
            labels.append((i, 1, int(bad)))
    rows += [(5000, None, "en", 7), (5001, "", "en", 7), (5001, "", "en", 7), (5002, "vileness " * 20_000, "en", 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, segments int")
    label_df = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = toxicity.score_documents(docs, label_df).collect()
    assert len(got) == len(rows)
    by_id = {r["doc_id"]: r for r in got}
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    right = sum(by_id[i]["predicted"] == int(i % 8 == 0) for i in range(1200))
    assert right >= 1190 and by_id[5000]["score"] == by_id[5001]["score"] < 0.3
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3) for r in got)
    hit = next(r for r in got if r["n_passages"])
    assert all(0 <= p["begin"] < p["end"] for p in hit["passages"])
    assert toxicity.score_documents(docs.where("false"), label_df).count() == 0
    assert {r["score"] for r in toxicity.score_documents(docs.limit(5), label_df.where("false")).collect()} == {0.0}
