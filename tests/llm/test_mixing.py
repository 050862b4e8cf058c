import random

from pyspark.sql import functions as F

from carrierpath.llm import mixing


def filled(sizes: list[int], weights: list[float], cap: int) -> list[float]:
    """Targets by reshaping until no source is above its cap."""
    total, fixed = float(sum(sizes)), {}
    while True:
        free = [i for i in range(len(sizes)) if i not in fixed]
        left, weight = total - sum(fixed.values()), sum(weights[i] for i in free)
        over = [i for i in free if weights[i] * left / weight > cap * sizes[i] + 1e-9]
        if not over:
            return [fixed.get(i, weights[i] * left / weight if i not in fixed else 0) for i in range(len(sizes))]
        fixed.update({i: float(cap * sizes[i]) for i in over})


def test_targets_match_resharing(spark):
    rng = random.Random(3)
    for _ in range(6):
        sizes = [rng.choice([0, 1, 5, 40, 300, 9000]) for _ in range(rng.randint(1, 9))]
        if not sum(sizes):
            sizes[0] = 7
        rows = [(f"s{i}", n) for i, n in enumerate(sizes)]
        got = {r["source"]: r["target"] for r in mixing.source_targets(spark.createDataFrame(rows, "source string, size long")).collect()}
        want = filled(sizes, [(1.0, 2.0, 3.0)[i % 3] for i in range(len(sizes))], 3)
        for (name, _), target in zip(rows, want, strict=True):
            assert abs(got[name] - target) < 1e-6 * max(1, target)
        assert abs(sum(got.values()) - sum(sizes)) < 1e-6 * sum(sizes)


def test_mix_follows_keys_and_budgets(spark):
    rng = random.Random(8)
    rows = [(i, "w " * rng.randint(0, 30), None, rng.choice(["a", "a", "a", "b", None]), 0) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for buckets in (1, 7, 2048):
        got = mixing.mix(docs, buckets=buckets).collect()
        assert len(got) == 400
        by = {}
        for r in got:
            by.setdefault(r["source"], []).append(r)
            assert r["taken"] == r["copies"] * r["size"] and 0 <= r["copies"] <= 3
        for own in by.values():
            assert abs(sum(r["taken"] for r in own) - own[0]["target"]) <= 30
        if buckets == 1:
            first = {(r["doc_id"], r["taken"]) for r in got}
        assert {(r["doc_id"], r["taken"]) for r in got} == first


def test_better_rows_are_taken_more_often(spark):
    docs = spark.createDataFrame([(i, "a b c d", "x", "s" if i % 2 else "t", 0) for i in range(2000)], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(i, int(i % 4 == 0), 0) for i in range(2000)], "doc_id long, quality int, toxic int")
    got = mixing.mix(docs, labels=labels, weights=(3.0, 1.0)).where("source = 't'").groupBy((F.col("doc_id") % 4 == 0).alias("good")).agg(F.avg("copies").alias("c")).collect()
    share = {r["good"]: r["c"] for r in got}
    assert share[True] > share[False] + 0.1


def test_edges(spark):
    schema = "doc_id long, text string, source string, key string, size int"
    assert mixing.mix(spark.createDataFrame([], schema)).count() == 0
    rows = [(1, None, "a", "k", 1), (1, None, "a", "k", 1), (2, "x", None, None, 2), (None, "y z", "b", None, 3)]
    got = mixing.mix(spark.createDataFrame(rows, schema)).collect()
    assert len(got) == 4 and sum(r["size"] for r in got) == 3
