import hashlib
import random

from carrierpath.llm import minhash


def test_likeness_estimates_jaccard():
    rng = random.Random(2)
    perms = minhash.Permutations()
    for share in (0.2, 0.5, 0.8, 1.0):
        base = [str(rng.random()) for _ in range(400)]
        other = base[: int(400 * share)] + [str(rng.random()) for _ in range(400 - int(400 * share))]
        a, b = (minhash.shingles(" ".join(t)) for t in (base, other))
        true = len(set(a) & set(b)) / len(set(a) | set(b))
        assert abs(minhash.alike(perms.signature(a), perms.signature(b)) - true) < 0.15


def test_words_and_case():
    a, b = minhash.shingles("The  quick\tbrown fox jumps é"), minhash.shingles("the quick brown FOX jumps é")
    assert a.tolist() == b.tolist() and len(a) == 2
    assert len(minhash.shingles("one two")) == 1 and len(minhash.shingles(" \n")) == 0
    assert minhash.shingles("a b c d e").tolist() != minhash.shingles("a b c d e").tolist()


def test_edited_rows_in_id_order(spark):
    rng = random.Random(5)
    rows = [(i * 7 - 50, "".join(rng.choice("ab é\n") for _ in range(rng.choice([0, 1, 3, 4, 50, 400])))) for i in range(60)]
    rows[10] = (rows[10][0], None)
    rng.shuffle(rows)
    docs = spark.createDataFrame([(*r, 5) for r in rows], "doc_id int, text string, range int").repartition(7)
    got = {r["doc_id"]: r for r in minhash.edited_fingerprints(docs).collect()}
    rows.sort()
    prints = {r["doc_id"]: r["fingerprint"] for r in minhash.fingerprints(docs).collect()}
    for k, (i, t) in enumerate(rows):
        t, nxt = t or "", rows[(k + 1) % len(rows)][1] or ""
        q = len(t) // 4
        edited = t[: len(t) - q] + nxt[:q]
        assert got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest() and got[i]["n_chars"] == len(t)
        assert got[i]["fingerprint"] == prints[i]
        assert got[i]["near_next"] == minhash.alike(minhash.from_text(prints[i]), minhash.from_text(prints[rows[(k + 1) % len(rows)][0]]))


def test_edges(spark):
    assert minhash.edited_fingerprints(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    one = minhash.edited_fingerprints(spark.createDataFrame([(1, "abcd efgh")], "doc_id long, text string")).collect()
    assert len(one) == 1 and one[0]["near_next"] == 1.0
    twice = spark.createDataFrame([(1, "a b"), (1, "a b"), (None, "c"), (2, "x" * 200_000)], "doc_id long, text string")
    assert minhash.edited_fingerprints(twice).count() == 4
