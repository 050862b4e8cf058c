import random

import numpy as np
import pytest

from carrierpath.operators import baselines, ops, rows


def test_two_alternatives_of_one_haplotype(spark):
    calls = spark.createDataFrame([(7, 1, 0), (7, 2, 0), (7, 2, 3), (7, 2, 3), (8, 1, 1)], "site_id long, alt_no int, hap_id long")
    sites = baselines.site_major(calls)
    assert sorted(r["hap_id"] for r in baselines.carriers_scan(sites, 7, 2).collect()) == [0, 3]
    assert {(r["site_id"], r["alt_no"]): r["k"] for r in baselines.frequency_scan(sites, 4).collect()} == {(7, 1): 1, (7, 2): 2, (8, 1): 1}


def test_runs_match_a_plain_sort_of_reversed_prefixes(spark):
    rng = random.Random(2)
    h, block = 12, 4
    sites = [("c2" if i % 3 == 0 else "c1", i, (i * 37) % 50) for i in range(11)]  # some share a position
    inc = sorted({(a, rng.randrange(h)) for _, a, _ in sites for _ in range(5)})
    got = baselines.prefix_sorted_runs(
        spark.createDataFrame(inc, "allele_id long, hap_id long"), spark.createDataFrame(sites, "contig string, allele_id long, pos long"), h, block
    ).collect()
    order = sorted(sites, key=lambda s: (s[0], s[2], s[1]))
    want = {}
    for b in range(0, len(order), block):
        has = [np.array([(a, x) in set(inc) for x in range(h)]) for _, a, _ in order[b : b + block]]
        runs = 0
        for i, column in enumerate(has):
            by = sorted(range(h), key=lambda x: [has[j][x] for j in range(i - 1, -1, -1)])  # stable: ties in the order of ids
            runs += 1 + sum(column[x] != column[y] for x, y in zip(by, by[1:], strict=False))
        want[b // block] = (len(has), runs)
    assert {r["block"]: (r["sites"], r["runs"]) for r in got} == want


def test_cohort_filter_without_required_alleles(spark):
    inc = spark.createDataFrame([(1, 0), (1, 2), (2, 2), (2, 3)], "allele_id long, hap_id long").selectExpr("*", "'x' as class")
    enc = rows.encode(inc, 5)
    got = lambda **k: sorted(r["hap_id"] for r in ops.cohort_filter(enc, **k).collect())
    assert got(exclude=[1], h=5) == [1, 3, 4] and got(h=5) == [0, 1, 2, 3, 4]
    assert got(require=[1, 1, 2]) == got(require=[1, 1, 2], early_stop=True) == [2]
    assert got(any_of=[1, 2], exclude=[2]) == [0]
    with pytest.raises(ValueError):
        ops.cohort_filter(enc, exclude=[1])
