import random
import re

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from carrierpath.llm import links, minhash, ngram_join


def grams(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if len(w) < 5:
        return frozenset([tuple(w)]) if w else frozenset()
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4))


def brute(rows):
    sets = {i: grams(t) for i, t in rows}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def corpus(seed, n=120):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 5)))
    passage = " ".join(word() for _ in range(20))
    bases = [[word() for _ in range(rng.choice([3, 6, 30, 80, 300]))] for _ in range(15)]
    out = []
    for _ in range(n):
        t = list(rng.choice(bases))
        for _ in range(rng.randint(0, max(1, len(t) // 25))):
            t[rng.randrange(len(t))] = word()
        s = " ".join(t)
        out.append(s.upper() if rng.random() < 0.1 else s + (" " + passage if rng.random() < 0.4 else ""))
    return [(i, t) for i, t in enumerate(out + ["", None, " \n ", "one", "One", passage, passage])]


def test_classes_match_brute_force(spark):
    for seed in (1, 2, 3):
        rows = corpus(seed)
        docs = spark.createDataFrame([(*r, 1, b"k") for r in rows], "doc_id long, text string, n int, key binary").repartition(5)
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.join_classes(docs).collect()}
        assert got == brute(rows)


def variants(seed, n=90):
    """Copies of one text, some with a few edits and some with so many that most pairs of them are not similar, around the threshold."""
    rng = random.Random(seed)
    base = [f"w{i}" for i in range(120)]
    out = []
    for i in range(n):
        t = list(base)
        for _ in range(rng.choice([0, 1, 2, 2, 3, 3])):
            t[rng.randrange(len(t))] = f"e{rng.randrange(6)}"
        out.append((i, " ".join(t)))
    return out


def test_families_in_blocks_match_brute_force(spark):
    for seed, docs, hashes in ((1, 7, 1 << 20), (2, 1000, 900), (3, 1000, 1 << 20)):
        rows = variants(seed)
        texts = spark.createDataFrame(rows, "doc long, text string").repartition(3)
        sets = ngram_join.whole_sets(texts).checkpoint()
        # All lists, and no rounds that leave little over: every document in one family.
        lists = ngram_join.rare_first_lists(sets).checkpoint()
        got = {r["doc"]: r["class"] for r in links.classes(lists, sets, docs=docs, hashes=hashes).collect()}
        want = {i: c for i, (_, c) in brute(rows).items()}
        assert {i: got.get(i, i) for i in want} == want
        left = lists.withColumn("class", lists.doc).withColumn("first", F.min("doc").over(Window.partitionBy("key")))
        found = links.family_links(left.checkpoint(), sets, left.count(), 80, docs, hashes).collect()
        root = {r["doc"]: r["root"] for r in links.components(spark.createDataFrame(found)).collect()}
        assert {i: root.get(i, i) for i in want} == want and len(found) < len(rows) * 20


def test_partners_match_brute_force():
    rng = np.random.default_rng(3)
    for _ in range(60):
        base = np.unique(rng.integers(0, 400, rng.integers(1, 120)))
        sets = [np.unique(np.concatenate([rng.choice(base, rng.integers(0, len(base) + 1), replace=False), rng.integers(0, 400, rng.integers(0, 8))])) for _ in range(25)]
        index = links.Inverted(sets)
        for q in sets:
            want = [j for j, s in enumerate(sets) if len(q) and 100 * len(np.intersect1d(q, s)) >= 80 * len(np.union1d(q, s))]
            assert sorted(index.partners(q, 80).tolist()) == want


def test_one_of_each_and_edges(spark):
    rows = corpus(4, 40)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = {i for i, (_, c) in brute(rows).items() if c == i}
    assert {r["doc_id"] for r in ngram_join.one_of_each(docs).collect()} == want
    assert ngram_join.join_classes(docs.where("false")).count() == 0
    odd = spark.createDataFrame([(None, "a b c d e f"), (3, "a b c d e f"), (3, "a b c d e f"), (2, "x " * 30_000)], "doc_id long, text string")
    got = ngram_join.join_classes(odd).collect()
    assert len(got) == 4 and {r["component_id"] for r in got if r["n_shingles"] == 2} == {3}


def test_divide_skip_matches_counting():
    rng = np.random.default_rng(0)
    for _ in range(200):
        lists = [np.unique(rng.integers(0, 60, rng.integers(0, 50))) for _ in range(rng.integers(1, 25))]
        least = int(rng.integers(1, len(lists) + 1))
        docs, n = np.unique(np.concatenate(lists), return_counts=True)
        got_docs, got_n = links.divide_skip(lists, least)
        order = np.argsort(got_docs)
        assert got_docs[order].tolist() == docs[n >= least].tolist() and got_n[order].tolist() == n[n >= least].tolist()


def test_components_match_union_find(spark):
    rng = random.Random(6)
    edges = [(rng.randrange(80), rng.randrange(80)) for _ in range(60)] + [(i, i + 1) for i in range(100, 140)]
    root = {}

    def find(i):
        root.setdefault(i, i)
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    got = {r["doc"]: r["root"] for r in links.components(spark.createDataFrame(edges, "x long, y long")).collect()}
    assert got == {i: find(i) for a, b in edges if a != b for i in (a, b)}


def test_minhash_near_duplicates_are_links(spark):
    rows = corpus(5)
    want = {i: c for i, (_, c) in brute(rows).items()}
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(got[i] != want[i] for i in want) <= 2  # bands may miss a link, never invent one
    assert all(want[i] == want[got[i]] for i in got)
