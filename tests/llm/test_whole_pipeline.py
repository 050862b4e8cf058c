"""run() over a small corpus against plain Python, SQL and the tiktoken library, stage after stage."""

import hashlib
import re
from collections import Counter
from itertools import combinations

import duckdb
import pandas as pd
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F
from tiktoken.load import load_tiktoken_bpe

import corpus_pipeline
from carrierpath.llm import toxicity
from carrierpath.llm.oracles import OP6
from carrierpath.llm.queries import VOCABULARY

from .conftest import DOCS

GIVEN = "/root/testdata/sf0.001"


def shingles(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def first_of_texts(docs):
    """Of equal normalised texts the row with the least id; one without an id only if none has one."""
    best = {}
    for row in docs:
        body = re.sub(r"[\x20\x09-\x0D]+", " ", row["text"] or "")
        order = (row["doc_id"] is None, row["doc_id"] or 0)
        if body not in best or order < best[body][0]:
            best[body] = (order, row)
    return [row for _, row in best.values()]


def first_of_classes(docs):
    sets, above = [shingles(r["text"]) for r in docs], list(range(len(docs)))

    def top(i):
        while above[i] != i:
            i = above[i]
        return i

    for i, j in combinations(range(len(docs)), 2):
        if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
            above[top(i)] = top(j)
    classes = {}
    for i, row in enumerate(docs):
        classes.setdefault(top(i), []).append(row)
    return [min(rows, key=lambda r: (r["doc_id"] is None, r["doc_id"] or 0)) for rows in classes.values()]


def mixed(docs, labels):
    """Rows as often as the SQL of operator 6 takes them."""
    con = duckdb.connect()
    con.register("documents", pd.DataFrame({"doc_id": pd.array([r["doc_id"] for r in docs], "Int64"), "text": [r["text"] for r in docs], "source": [r["source"] for r in docs]}))
    con.register("labels", labels)
    times = dict(con.execute(OP6.replace("(copies * size)::BIGINT AS taken", "copies").replace("size, source_size, round(target, 6) AS target, ", "")).fetchall())
    return [row for row in docs for _ in range(times[row["doc_id"]])]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The given documents with an exact copy, a near copy, a row without an id, a repeated row and an empty text beside them."""
    folder = str(tmp_path_factory.mktemp("corpus"))
    docs = spark.read.parquet(f"{GIVEN}/documents.parquet").select(*(F.col(c.split()[0]).cast(c.split()[1]) for c in DOCS.split(", ")))
    long = docs.orderBy(F.desc("n_chars"), "doc_id").first()
    words = "a plain text of words that nobody else in this corpus has written down before now"
    more = [
        (900_001, long["text"].replace(" ", "  "), "en", "planted", 0), (900_002, long["text"] + " tail", "en", "planted", 0), (None, words, "en", None, 0),
        (900_003, "x " + words, "en", "planted", 0), (900_003, "x " + words, "en", "planted", 0), (900_004, None, "en", "planted", 0), (900_005, "", "en", "planted", 0),
    ]
    docs.unionByName(spark.createDataFrame(more, DOCS)).repartition(3).write.parquet(f"{folder}/documents.parquet")
    spark.read.parquet(f"{GIVEN}/labels.parquet").write.parquet(f"{folder}/labels.parquet")
    return folder


def test_run_equals_brute_force(spark, folder):
    docs, labels = (spark.read.parquet(f"{folder}/{x}.parquet") for x in ("documents", "labels"))
    scored = toxicity.score_documents(docs, labels, keep=corpus_pipeline.COLUMNS)
    clean = [r["row"].asDict() for r in scored.where("predicted = 0").collect()]
    single = first_of_texts(clean)
    apart = first_of_classes(single)
    assert len(apart) < len(single) < len(clean) < docs.count()
    encoder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=load_tiktoken_bpe(public_tokenizers.path(VOCABULARY)), special_tokens={})
    want = Counter()
    for row in mixed(apart, labels.toPandas()):
        ids = encoder.encode_ordinary(row["text"] or "")
        want[row["doc_id"], len(ids), hashlib.sha256(b"".join(i.to_bytes(4, "little") for i in ids)).hexdigest(), hashlib.sha256((row["text"] or "").encode()).hexdigest()] += 1
    got = Counter(tuple(r) for r in corpus_pipeline.run(spark, folder).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256").collect())
    assert got == want


def test_run_over_an_empty_table(spark, folder, tmp_path):
    spark.read.parquet(f"{folder}/documents.parquet").limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{folder}/labels.parquet").limit(0).write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
