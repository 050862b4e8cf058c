"""Toxic passages by maximum-scoring segment search over token log-odds.

1. Log-odds between toxic and other labelled texts, with an informative Dirichlet prior
   from both together, for words and for their beginnings, as inflected words share a
   stem. A word scores the log-odds of the best supported entry that matches it, if that
   entry exceeds ``Z_LEAST`` standard errors; all other words score a small negative drift.
2. One linear scan of each whole text finds all maximal scoring segments (Ruzzo and Tompa).
3. Extreme-value statistics turn a segment score S in a text of n tokens into the number of such
   segments expected by chance, K n exp(-lambda S): lambda solves E[exp(lambda s)] = 1 over the
   tokens of other texts, K is its maximum-likelihood value over those texts' best
   segments. Segments expected less than ``SIGNIFICANT`` times are toxic passages; a text's
   evidence is the sum of their normalised scores.
4. A logistic curve over the evidence, fitted to the labels, gives the score.

Labels are learnt from at most ``TRAIN_ROWS`` labelled rows, those with the smallest hashes,
and never from rows whose crc32 of the id as text leaves 2 modulo 4. Everything else covers all rows.

Null texts count as empty, an empty text has no evidence and gets the score of no
evidence, repeated rows score alike, several labels of one id count as the highest,
and without labels every score is 0.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.memory import trimmed
from .common import cut, text_of

#: Most labelled rows that the model is fitted on; it holds all their entries that pass the tests.
TRAIN_ROWS = 40_000
#: Least standard errors, count and log-odds of a scoring entry; weight of the prior as a share of all counts.
Z_LEAST, COUNT_LEAST, DELTA_LEAST, PRIOR_SHARE = 4.0, 3, 1.5, 0.05
#: Lengths of word beginnings that are entries of their own.
STEMS = (4, 5, 6, 7)
#: Score of a token that is not in the model.
DRIFT = -0.1
#: A segment expected less often than this by chance is significant.
SIGNIFICANT = 0.05
#: Words whose score a task remembers.
REMEMBERED = 1 << 16
#: Scores from here on are predicted toxic.
THRESHOLD = 0.3

_WORD = re.compile(r"[^\W\d_]+")


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def tokens(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def segments(hits: list[tuple[int, float]], drift: float = DRIFT) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (first, last, score) of a sequence given by its positive tokens.

    ``hits`` has (place, score) in order; every place between scores ``drift``. Each hit is
    looked at once and merges remove what they join, so the scan is linear.
    """
    kept: list[list] = []  # first, last, sum before it, sum through it, nearest earlier segment with a smaller sum before
    total, at = 0.0, 0
    for place, score in hits:
        total += drift * (place - at)
        first, before = place, total
        total += score
        at = place + 1
        own = [first, place, before, total]
        while True:
            j = len(kept) - 1
            while j >= 0 and kept[j][2] >= own[2]:
                j = kept[j][4]
            if j < 0 or kept[j][3] >= own[3]:
                kept.append([*own, j])
                break
            own = [kept[j][0], own[1], kept[j][2], own[3]]
            del kept[j:]
    return [(a, b, s1 - s0) for a, b, s0, s1, _ in kept]


def training_labels(labels: DataFrame, most: int = TRAIN_ROWS) -> DataFrame:
    """(doc_id, toxic) of at most ``most`` labelled rows that may be learnt from."""
    own = labels.where(F.col("toxic").isNotNull() & ~held_out(F.col("doc_id")))
    one = own.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    return one.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)


def entries(word: str) -> list[str]:
    """The word and its beginnings, each marked by a star."""
    return [word, *(word[:k] + "*" for k in STEMS if len(word) >= k)]


def training_texts(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS) -> DataFrame:
    """(doc_id, text, toxic): the rows of docs (doc_id, text) with a training label, read once."""
    return cut(docs.select("doc_id", text_of().alias("text")).join(F.broadcast(training_labels(labels, most)), "doc_id"))


def token_counts(texts: DataFrame) -> DataFrame:
    """(token, toxic, other): in how many different toxic and other texts of (text, toxic) each entry stands.

    Texts count, not places, and copies count once: a repeated line or a copied text
    says no more about its words than one.
    """
    once = texts.groupBy(F.xxhash64("text").alias("h"), F.length("text").alias("n")).agg(F.min("text").alias("text"), F.max("toxic").alias("toxic"))

    def run(batches):
        words = (Counter(), Counter())
        for b in batches:
            for text, toxic in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                words[1 - toxic].update(set(tokens(text)))
        counts = (Counter(), Counter())
        for own, out in zip(words, counts, strict=True):
            for w, n in own.items():
                for e in entries(w):
                    out[e] += n  # of a beginning: texts and words in them
        both = sorted(counts[0].keys() | counts[1].keys())
        for at in range(0, len(both), 50_000):
            part = both[at : at + 50_000]
            yield pa.record_batch([pa.array(part, pa.string()), *(pa.array([c[t] for t in part], pa.int64()) for c in counts)], names=["token", "toxic", "other"])

    partial = once.select("text", (F.col("toxic") > 0).cast("int").alias("toxic")).mapInArrow(trimmed(run), "token string, toxic long, other long")
    return partial.groupBy("token").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))


def log_odds(counts: DataFrame, prior: float = PRIOR_SHARE) -> DataFrame:
    """(token, toxic, other, delta, z, p_other): log-odds with a Dirichlet prior shaped like both classes together."""
    word = ~F.col("token").endswith("*")
    sums = counts.where(word).agg(F.sum("toxic").alias("n1"), F.sum("other").alias("n0"))
    n1, n0 = F.col("n1"), F.col("n0")
    held = F.lit(prior) * (n1 + n0)
    y1 = F.col("toxic") + F.lit(prior) * (F.col("toxic") + F.col("other"))
    y0 = F.col("other") + F.lit(prior) * (F.col("toxic") + F.col("other"))
    delta = F.log(y1 / (n1 + held - y1)) - F.log(y0 / (n0 + held - y0))
    return (
        counts.join(F.broadcast(sums))  # one row
        .withColumn("delta", delta)
        .withColumn("z", F.col("delta") / F.sqrt(1 / y1 + 1 / y0))
        .withColumn("p_other", y0 / (n0 + held))
        .select("token", "toxic", "other", "delta", "z", "p_other")
    )


class Model:
    """Scores of entries, words that are spared, and the decay rate lambda of chance segments."""

    def __init__(self, rows, spared=(), drift: float = DRIFT):
        self.entry = {r["token"]: (r["z"], r["delta"] + drift) for r in rows}
        self.spared = frozenset(spared)
        self.drift = drift
        parts = [(r["p_other"], r["delta"] + drift) for r in rows]
        rest = max(0.0, 1 - sum(p for p, _ in parts))
        # The positive root of E[exp(lambda s)] = 1; where chance tokens hardly score it is large.
        low, high = 1e-6, 20.0
        for _ in range(80):
            mid = (low + high) / 2
            if sum(p * math.exp(min(700.0, mid * s)) for p, s in parts) + rest * math.exp(mid * drift) < 1:
                low = mid
            else:
                high = mid
        self.decay = low

    def score(self, word: str) -> float:
        """Score of a word, 0 if none of its entries counts."""
        if word in self.spared:
            return 0.0
        found = [self.entry[e] for e in entries(word) if e in self.entry]
        return max(found)[1] if found else 0.0


def fit(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS) -> Model:
    """Token model from docs (doc_id, text) and labels (doc_id, toxic)."""
    return fit_texts(training_texts(docs, labels, train_rows))


def fit_texts(texts: DataFrame) -> Model:
    """Token model from labelled texts (text, toxic)."""
    odds = log_odds(cut(token_counts(texts)))
    best = odds.where((F.col("z") >= Z_LEAST) & (F.col("toxic") >= COUNT_LEAST) & (F.col("delta") >= DELTA_LEAST))
    rows = best.orderBy(F.desc("z"), "token").select("token", "delta", "z", "p_other").collect()
    # Words that other texts use, though their beginnings are those of toxic words.
    stems = F.array(*[F.concat(F.substring("token", 1, k), F.lit("*")) for k in STEMS])
    spared = odds.where(~F.col("token").endswith("*") & (F.col("other") >= COUNT_LEAST) & (F.col("delta") <= 0)).select("token", F.explode(stems).alias("stem"))
    known = best.where(F.col("token").endswith("*")).select(F.col("token").alias("stem"))
    spared = spared.join(known, "stem", "left_semi").select("token").distinct()
    return Model(rows, [r["token"] for r in spared.collect()] if rows else [])


def passages(docs: DataFrame, model: Model, with_text: bool = False) -> DataFrame:
    """(doc_id, n_tokens, segments): all maximal scoring segments of each whole text of docs (doc_id, text, ...) with their character ranges.

    The columns after the first two pass through, and the text does if ``with_text``.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    first = 1 if with_text else 2
    more = docs.columns[first:]

    def run(batches):
        drift, score = sent.value.drift, sent.value.score
        known: dict[str, float] = {}
        for b in batches:
            counts, found = [], []
            for text in b.column(1).to_pylist():
                text = text or ""
                own = tokens(text)
                counts.append(len(own))
                words = set(own)
                if len(known) + len(words) > REMEMBERED:
                    known = {}
                known.update((w, score(w)) for w in words if w not in known)
                hits = [(i, s) for i, t in enumerate(own) if (s := known[t])]
                if not hits:
                    found.append([])
                    continue
                made = segments(hits, drift)
                place = [m.span() for m in _WORD.finditer(text.lower())]
                found.append([{"begin": place[x][0], "end": place[y][1], "score": s} for x, y, s in made])
            kind = pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32()), ("score", pa.float64())]))
            yield pa.record_batch([b.column(0), pa.array(counts, pa.int64()), pa.array(found, kind), *b.columns[first:]], names=["doc_id", "n_tokens", "segments", *more])

    fields = docs.schema.fields
    segment = T.StructType().add("begin", T.IntegerType()).add("end", T.IntegerType()).add("score", "double")
    made = T.StructType().add("n_tokens", "long").add("segments", T.ArrayType(segment))
    return docs.mapInArrow(trimmed(run), T.StructType([fields[0], *made.fields, *fields[first:]]))


def _logistic(bins: list[tuple[float, int, int]]) -> tuple[float, float]:
    """Intercept and slope by Newton steps on (x, positives, all), slightly held back so that separable data stay finite."""
    a, b = 0.0, 0.0
    for _ in range(100):
        ga, gb, haa, hab, hbb = -1e-3 * a, -1e-2 * b, 1e-3, 0.0, 1e-2
        for x, pos, n in bins:
            p = 1 / (1 + math.exp(-max(-30.0, min(30.0, a + b * x))))
            w = n * p * (1 - p)
            ga, gb = ga + pos - n * p, gb + (pos - n * p) * x
            haa, hab, hbb = haa + w, hab + w * x, hbb + w * x * x
        det = haa * hbb - hab * hab
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        step = min(1.0, 4.0 / max(abs(da), abs(db), 1e-12))
        a, b = a + step * da, b + step * db
        if max(abs(da), abs(db)) < 1e-9:
            break
    return a, b


def score_documents(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", train_rows: int = TRAIN_ROWS, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, held_out, score, predicted, n_passages, passages), one row per row of ``docs``; with a struct ``row`` of its columns ``keep`` if any.

    ``passages`` lists the significant toxic passages with their character ranges in
    the lower-cased text. The training rows are read once and fit everything; all rows then pass one map, without a shuffle.
    """
    own = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), *[F.col(c).alias(f"_{i}") for i, c in enumerate(keep) if c != text_col])
    train = training_texts(own, labels, train_rows)
    model = fit_texts(train)
    seen = cut(passages(train.select("doc_id", "text", "toxic"), model))
    best = F.coalesce(F.array_max(F.col("segments.score")), F.lit(0.0))
    k = seen.where("toxic = 0").agg(
        (F.count(F.lit(1)) / F.sum(F.greatest(F.col("n_tokens"), F.lit(1)) * F.exp(-F.lit(model.decay) * best))).alias("k")
    ).first()["k"]
    k = min(1.0, k or 1.0)
    norm = lambda s: F.lit(model.decay) * s["score"] - F.log(F.lit(k) * F.greatest(F.col("n_tokens"), F.lit(1)))
    toxic = F.filter("segments", lambda s: norm(s) > -math.log(SIGNIFICANT))
    evidence = F.least(F.log1p(F.aggregate(toxic, F.lit(0.0), lambda acc, s: acc + norm(s))), F.lit(20.0))
    bins = seen.groupBy(F.round(evidence, 2).alias("x")).agg(F.sum((F.col("toxic") > 0).cast("long")).alias("pos"), F.count(F.lit(1)).alias("n")).collect()  # at most 2001 bins
    if bins:
        a, b = _logistic(sorted((r["x"], r["pos"], r["n"]) for r in bins))
        score = 1 / (1 + F.exp(-(F.lit(a) + F.lit(max(b, 0.0)) * evidence)))
    else:
        score = F.lit(0.0)
    row = [F.struct(*[F.col("text" if c == text_col else f"_{i}").alias(c) for i, c in enumerate(keep)]).alias("row")] if keep else []
    return passages(own, model, with_text=text_col in keep).withColumn("score", score).withColumn("passages", toxic).select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "score",
        (F.col("score") >= THRESHOLD).cast("int").alias("predicted"),
        F.size("passages").alias("n_passages"), "passages", *row,
    )
