"""The field of operator 8 and the token model of operator 10 against enumeration and plain Python."""

import itertools
import math
import random
from collections import Counter

import numpy as np

from carrierpath.llm import html_extract, toxicity


def path_score(emit, moves, start, end, labels):
    inner = sum(moves[a][b] for a, b in itertools.pairwise(labels))
    return start[labels[0]] + end[labels[-1]] + inner + sum(e for e, y in zip(emit, labels, strict=True) if y)


def test_viterbi_finds_the_best_of_all_labellings():
    rng = np.random.default_rng(3)
    for n in (1, 2, 5, 8, 9) * 8:
        found = [[f for f in "abcdef" if rng.random() < 0.4] + ["unknown"] for _ in range(n)]
        field = html_extract.Field({f: i for i, f in enumerate("abcdef")}, rng.normal(size=6), rng.normal(size=(2, 2)), rng.normal(size=2), rng.normal(size=2))
        score = lambda y: path_score(field.emit(found), field.moves, field.start, field.end, y)  # noqa: B023, E731
        assert math.isclose(score(field.decode(found)), max(map(score, itertools.product((0, 1), repeat=n))))
    assert field.decode([]) == []


def test_loss_and_gradient_equal_enumeration():
    rng = np.random.default_rng(4)
    sizes, width = (1, 3, 5, 6), 4
    x = np.zeros((len(sizes), max(sizes), width), dtype=np.float32)
    on = np.arange(max(sizes)) < np.array(sizes)[:, None]
    x[on] = rng.random((on.sum(), width)) < 0.5
    labels = [tuple(int(v) for v in rng.integers(0, 2, k)) for k in sizes]
    gold = np.zeros(width + 8)
    for own, y in zip(x, labels, strict=True):
        gold[:width] += sum(own[j] * v for j, v in enumerate(y))
        for a, b in itertools.pairwise(y):
            gold[width + 2 * a + b] += 1
        gold[width + 4 + y[0]] += 1
        gold[width + 6 + y[-1]] += 1

    def enumerated(theta):
        w, moves, start, end = theta[:width], theta[width : width + 4].reshape(2, 2), theta[width + 4 : width + 6], theta[width + 6 :]
        out = 0.0
        for own, y, k in zip(x, labels, sizes, strict=True):
            emit = own[:k] @ w
            out += np.logaddexp.reduce([path_score(emit, moves, start, end, z) for z in itertools.product((0, 1), repeat=k)]) - path_score(emit, moves, start, end, y)
        return out / len(sizes)

    theta = rng.normal(size=width + 8)
    value, slope = html_extract.loss(theta, x, on, gold)
    assert math.isclose(value, enumerated(theta), rel_tol=1e-5)
    step = 1e-4
    for i, part in enumerate(np.eye(width + 8) * step):
        assert math.isclose(slope[i], (enumerated(theta + part) - enumerated(theta - part)) / (2 * step), rel_tol=1e-3, abs_tol=1e-5)


def texts_of(n=300):
    rng = random.Random(9)
    words = [f"{a}{b}{c}o" for a in "bdfg" for b in "aeiu" for c in "lmnr"]
    rows = [(" ".join(rng.choices(words, k=rng.randint(0, 12)) + ["nastyword"] * rng.randint(0, 2) * (i % 3 == 0)), int(i % 3 == 0)) for i in range(n)]
    return rows + rows[:20] + [("", 0), ("", 1)]


def test_counts_and_log_odds_equal_plain_python(spark):
    rows = texts_of()
    texts = spark.createDataFrame(rows, "text string, toxic int").repartition(3)
    label = {}
    for text, toxic in rows:
        label[text] = max(label.get(text, 0), toxic)
    counts = {True: Counter(), False: Counter()}
    for text, toxic in label.items():
        for word in set(toxicity.tokens(text)):
            counts[bool(toxic)].update(toxicity.entries(word))
    counted = toxicity.token_counts(texts)
    assert {r["token"]: (r["toxic"], r["other"]) for r in counted.collect()} == {t: (counts[True][t], counts[False][t]) for t in counts[True] | counts[False]}
    n1, n0 = (sum(v for t, v in counts[c].items() if not t.endswith("*")) for c in (True, False))
    prior = toxicity.PRIOR_SHARE
    held = prior * (n1 + n0)
    got = {r["token"]: r for r in toxicity.log_odds(counted).collect()}
    for token, row in got.items():
        both = prior * (counts[True][token] + counts[False][token])
        y1, y0 = counts[True][token] + both, counts[False][token] + both
        delta = math.log(y1 / (n1 + held - y1)) - math.log(y0 / (n0 + held - y0))
        assert math.isclose(row["delta"], delta, rel_tol=1e-9, abs_tol=1e-9)
        assert math.isclose(row["z"], delta / math.sqrt(1 / y1 + 1 / y0), rel_tol=1e-9, abs_tol=1e-9) and math.isclose(row["p_other"], y0 / (n0 + held), rel_tol=1e-9)


def test_decay_is_the_root_of_the_generating_function():
    rows = [{"token": f"w{i}", "z": 4.0, "delta": 1.0 + i / 4, "p_other": 0.0004 * (i + 1)} for i in range(6)]
    model = toxicity.Model(rows)
    scores = [(r["p_other"], r["delta"] + model.drift) for r in rows]
    mean = sum(p * math.exp(model.decay * s) for p, s in scores) + (1 - sum(p for p, _ in scores)) * math.exp(model.decay * model.drift)
    assert math.isclose(mean, 1.0, rel_tol=1e-9)


def test_logistic_is_the_maximum_of_the_held_back_likelihood():
    bins = [(-2.0, 1, 40), (-0.5, 5, 30), (0.5, 14, 25), (2.0, 19, 20)]

    def value(a, b):
        return sum(pos * (a + b * x) - n * math.log1p(math.exp(a + b * x)) for x, pos, n in bins) - 0.5e-3 * a * a - 0.5e-2 * b * b

    a, b = toxicity._logistic(bins)
    assert all(value(a, b) > value(a + da, b + db) for da, db in ((1e-3, 0), (-1e-3, 0), (0, 1e-3), (0, -1e-3), (1e-3, 1e-3), (-1e-3, -1e-3)))
    assert all(math.isfinite(v) for v in toxicity._logistic([(-1.0, 0, 50), (1.0, 50, 50)]))
