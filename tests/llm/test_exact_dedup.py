import hashlib
import random
import re

from carrierpath.llm import exact_dedup


def test_groups_match_brute_force(spark):
    rng = random.Random(1)
    texts = ["a  b", "a b", "a\tb", "A b", "", None, " ", "\n", "x" * 20_000] + [f"t {i % 40}" for i in range(300)] + ["hot copy"] * 200
    rng.shuffle(texts)
    rows = [(i, t, "extra") for i, t in enumerate(texts)]
    rows.append(rows[3])
    docs = spark.createDataFrame(rows, "doc_id long, text string, digest string")
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    groups = {}
    for i, t, _ in rows:
        groups.setdefault(norm(t), []).append(i)
    for heavy in (3, 64, 10**9):
        got = exact_dedup.duplicate_groups(docs, min_heavy=heavy).collect()
        assert len(got) == len(rows)
        by_id = dict((i, norm(t)) for i, t, _ in rows)
        for r in got:
            own = groups[by_id[r["doc_id"]]]
            assert (r["keep_id"], r["group_size"], r["kept"]) == (min(own), len(own), r["doc_id"] == min(own))
            assert r["text_sha256"] == hashlib.sha256(by_id[r["doc_id"]].encode()).hexdigest()
    assert exact_dedup.drop_duplicates(docs.dropDuplicates()).count() == len(groups)


def test_empty_table(spark):
    assert exact_dedup.duplicate_groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0
