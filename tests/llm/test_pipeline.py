import random
from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline
from carrierpath.llm import exact_dedup, mixing, ngram_join, toxicity
from carrierpath.llm.common import row_key

from .conftest import DOCS


def corpus(spark, folder, n=400):
    """Documents of which some bear toxic words in number, and labels that leave many in doubt."""
    rng = random.Random(5)
    mild = [f"mild{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(60)]
    docs, labels = [], []
    for i in range(n):
        bad = rng.choice([0, 0, 0, 0, 0, 0, 1, 2, 6])
        words = [rng.choice(mild) for _ in range(40)] + ["vile", "hateful"][: bad % 2 + 1] * bad
        rng.shuffle(words)
        docs.append((i, " ".join(words), "en", "s", 0))
        labels.append((i, 1, int(rng.random() < [0, 0.3, 0.4, 0, 0, 0, 0.95][bad])))
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return spark.createDataFrame(docs, DOCS)


def test_toxic_documents_go_by_the_operators_own_decision(spark, tmp_path):
    docs = corpus(spark, tmp_path)
    scored = toxicity.score_documents(docs, spark.read.parquet(f"{tmp_path}/labels.parquet")).collect()
    assert any(toxicity.THRESHOLD <= r["score"] < 0.5 for r in scored)
    got = {r["doc_id"] for r in corpus_pipeline.drop_toxic(spark, docs, str(tmp_path)).collect()}
    assert got == {r["doc_id"] for r in scored if r["predicted"] == 0} and 0 < len(got) < len(scored)


def counted(rows):
    return Counter((r["doc_id"], r["text"]) for r in rows)


def test_rows_without_id_are_judged_by_their_text(spark, tmp_path):
    docs = corpus(spark, tmp_path)
    scored = toxicity.score_documents(docs, spark.read.parquet(f"{tmp_path}/labels.parquet")).join(docs, "doc_id").collect()
    bad = max(scored, key=lambda r: r["score"])["text"]
    good = min(scored, key=lambda r: r["score"])["text"]
    some = spark.createDataFrame([(None, bad, "en", "s", 0), (None, good, "en", "s", 0), (None, good, "en", "s", 0), (None, "a lone text of six words", "en", "s", 0), (None, None, "en", None, 0)], DOCS)
    clean = corpus_pipeline.drop_toxic(spark, docs.unionByName(some), str(tmp_path)).where("doc_id is null")
    assert counted(clean.collect()) == {(None, good): 2, (None, "a lone text of six words"): 1, (None, None): 1}
    one = {(None, good): 1, (None, "a lone text of six words"): 1, (None, None): 1}
    for heavy in (2, 64):
        assert counted(exact_dedup.drop_duplicates(some.where("text <> '' or text is null").unionByName(docs.limit(0)), min_heavy=heavy).collect()) == one | {(None, bad): 1}
    near = spark.createDataFrame([(None, "one two three four five six seven eight nine ten " * 3, "en", "s", 0)], DOCS)
    got = ngram_join.one_of_each(some.unionByName(near).unionByName(near)).collect()
    assert counted(got) == one | {(None, bad): 1, (None, near.first()["text"]): 1}
    mixed = corpus_pipeline.mix_sources(spark, some.dropDuplicates(), str(tmp_path)).collect()
    assert {r["doc_id"] for r in mixed} == {None} and len(mixed) >= 3


def test_repeated_rows(spark, tmp_path):
    row, other = (1, "x y z u v w", "en", "a", 0), (2, "p q r s t u v", "en", "b", 0)
    near = "one two three four five six seven eight nine ten " * 3
    docs = spark.createDataFrame([row] * 40 + [other] + [(3, near, "en", "a", 0), (3, "quite another text under one id", "en", "b", 0), (4, "p q  r s t u v", "en", "b", 0), (5, near + "eleven", "en", "a", 0)], DOCS).repartition(4)
    for heavy in (2, 64):
        got = exact_dedup.drop_duplicates(docs, min_heavy=heavy).collect()
        assert counted(got) == {row[:2]: 1, other[:2]: 1, (3, near): 1, (3, "quite another text under one id"): 1, (5, near + "eleven"): 1}
    assert counted(ngram_join.one_of_each(docs).collect()) == {row[:2]: 1, other[:2]: 1, (3, near): 1, (3, "quite another text under one id"): 1}
    assert {r["component_id"] for r in ngram_join.join_classes(docs).where("doc_id = 5").collect()} == {3}
    corpus(spark, tmp_path, 5)
    docs = docs.withColumn("_row", row_key(F.col("doc_id"), F.col("text")))
    mixed = mixing.mix(docs, row_col="_row")
    want = {(r["doc_id"], r["text"]): r["n"] for r in mixed.groupBy("_row").agg(F.sum("copies").alias("n")).join(docs.dropDuplicates(["_row"]), "_row").where("n > 0").collect()}
    assert counted(mixing.mixed_rows(docs, mixed, "_row").collect()) == want and sum(want.values()) <= 3 * docs.count()
