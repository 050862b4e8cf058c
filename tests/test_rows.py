import random

import pytest
from pyspark.sql import functions as F

from carrierpath.functions import bitops
from carrierpath.operators import cost, incidence, ops, rows

SCHEMA = "allele_id long, hap_id long, class string"


def rel(spark, sets, cls="SNV"):
    return spark.createDataFrame([(a, h, cls) for a, hs in sets.items() for h in hs], SCHEMA)


def test_worked_rows(spark):
    inc = rel(spark, {1: [1], 2: [0, 5], 3: [0, 1, 5, 7]})
    got = {r["allele_id"]: r for r in rows.encode(inc, 8).collect()}
    assert [got[i]["bits"] for i in (1, 2, 3)] == [3, 6, 8]
    assert [got[i]["enc"] for i in (1, 2, 3)] == ["list", "list", "bitmap"]
    assert got[3]["words"] == [163]
    enc = rows.encode(inc, 8).cache()
    for how in ("merge", "and", "probe", "auto"):
        assert sorted(r["hap_id"] for r in ops.intersect(enc, 2, 3, 8, how).collect()) == [0, 5]
    assert [r["af"] for r in ops.frequency(enc, 8).orderBy("allele_id").collect()] == [0.125, 0.25, 0.5]


def test_break_even():
    real, whole = cost.break_even(400)
    assert round(real, 2) == 46.28 and whole == 44
    assert [bitops.id_width(h) for h in (1, 2, 3, 64, 65, 400, 1 << 31, (1 << 31) + 1)] == [1, 1, 2, 6, 7, 9, 31, 32]


def test_published_bitmap_bits(spark):
    counted = spark.range(24_921).select(F.col("id").alias("allele_id"), F.lit("SNV").alias("class"), F.lit(3).cast("long").alias("k"))
    counted = counted.unionByName(spark.range(45).select(F.col("id").alias("allele_id"), F.lit("SV").alias("class"), F.lit(1).cast("long").alias("k")))
    got = {r["class"]: r["bits_bitmap"] for r in cost.by_class(cost.per_row(counted, 400)).collect()}
    assert got == {"SNV": 9_968_400, "SV": 18_000}


@pytest.mark.parametrize("h", [1, 2, 63, 64, 65, 400])
def test_round_trip_and_costs(spark, h):
    rng = random.Random(h)
    sets = {a: rng.sample(range(h), rng.randint(1, h)) for a in range(12)}
    sets[99], sets[98] = list(range(h)), [h - 1]
    inc = rel(spark, sets)
    for policy in ("min_cost", "threshold", "list", "bitmap"):
        enc = rows.encode(inc, h, policy)
        assert {(r["allele_id"], r["hap_id"]) for r in rows.decode(enc).collect()} == {(a, x) for a, s in sets.items() for x in s}
    for r in cost.per_row(incidence.counts(inc), h).collect():
        assert r["bits_hybrid"] == min(r["bits_dense"], r["bits_list"])


def test_intersections_agree(spark):
    rng, h = random.Random(4), 130
    sets = {a: rng.sample(range(h), k) for a, k in enumerate((3, 17, 60, 130, 1))}
    enc = rows.encode(rel(spark, sets), h).cache()
    for a, b in ((0, 2), (1, 3), (2, 3), (0, 4)):
        want = sorted(set(sets[a]) & set(sets[b]))
        for how in ("merge", "and", "probe", "auto"):
            assert sorted(r["hap_id"] for r in ops.intersect(enc, a, b, h, how).collect()) == want


def test_cohort_filters(spark):
    sets = {1: [0, 1, 2, 3], 2: [1, 2, 9], 3: [2], 4: [7]}
    enc = rows.encode(rel(spark, sets), 10).cache()
    ids = lambda df: sorted(r["hap_id"] for r in df.collect())
    for stop in (False, True):
        assert ids(ops.cohort_filter(enc, require=[1, 2], early_stop=stop)) == [1, 2]
        assert ids(ops.cohort_filter(enc, require=[1, 2], exclude=[3], early_stop=stop)) == [1]
        assert ids(ops.cohort_filter(enc, require=[3, 4], early_stop=stop)) == []
        assert ids(ops.cohort_filter(enc, require=[1, 12], early_stop=stop)) == []
    assert ids(ops.cohort_filter(enc, any_of=[3, 4])) == [2, 7]


def test_merge_guards_alleles(spark):
    a, b = rows.encode(rel(spark, {1: [0]}), 8), rows.encode(rel(spark, {2: [0, 1]}, "SV"), 8)
    merged = rows.merge(a, b)
    assert merged.count() == 2 and merged.agg(F.sum("bits")).first()[0] == 9
    with pytest.raises(Exception, match="allele in both sets"):
        rows.merge(a, a).collect()


def test_threshold_can_cost_more(spark):
    counted = spark.createDataFrame([(1, 44), (2, 45), (3, 46), (4, 47)], "allele_id long, k long")
    best = {r["k"]: r["enc"] for r in cost.per_row(counted, 400).collect()}
    rule = {r["k"]: r["enc"] for r in cost.per_row(counted, 400, "threshold").collect()}
    assert best == {44: "list", 45: "bitmap", 46: "bitmap", 47: "bitmap"} and rule == {44: "list", 45: "list", 46: "list", 47: "bitmap"}


def test_no_python_and_no_cartesian_in_column_methods(spark):
    inc = rel(spark, {1: [1], 2: [0, 5]})
    plan = cost.by_class(cost.per_row(incidence.counts(inc, by=("class",)), 8))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Cartesian" not in plan


def test_varint_rows_round_trip(spark):
    rng = random.Random(3)
    h = 5_000_000
    want = {(a, x, "SNV") for a, n in (("one", 1), ("few", 7), ("many", 3000)) for x in rng.sample(range(h), n)} | {("edge", x, "SNV") for x in (0, 127, 128, 255, 16_511, h - 1)}
    inc = spark.createDataFrame(sorted(want) + sorted(want)[:50], "allele_id string, hap_id long, class string")
    got = rows.encode_varint(inc, h)
    assert {r["enc"] for r in got.collect()} == {"list"}
    assert sorted(tuple(r) for r in rows.decode_varint(got).collect()) == sorted((a, x) for a, x, _ in want)
    few = spark.createDataFrame([("a", x, "SNV") for x in range(0, 64, 2)] + [("b", 63, "SNV")], "allele_id string, hap_id long, class string")
    both = rows.encode_varint(few, 64)
    assert {r["allele_id"]: r["enc"] for r in both.collect()} == {"a": "bitmap", "b": "list"}
    assert rows.decode_varint(both).count() == 33
    assert rows.encode_varint(few.limit(0), 64).count() == 0
