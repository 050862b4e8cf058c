"""Runs against the rows of all nodes, and how many rows the queries on walks move."""

import random

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from carrierpath.operators import backbone, runs, walks
from carrierpath.plans.session import cut


def both(spark, seed):
    """Overlaps, insertions, variants beyond the region, two at one place, whole contigs replaced, several contigs."""
    r = random.Random(seed)
    contigs = ["c1", "c2"][: 1 + seed % 2]
    rows = [(r.choice(contigs), i, r.choice([-50, 0, 100, 200, 300, 300, 400, 950, 1000, 1200]), r.choice([0, 0, 50, 100, 250, 1000]), "SV") for i in range(8)]
    rows += [(c, 90 + i, 10 * i, 1, "SNV") for i, c in enumerate(contigs)]
    alleles = spark.createDataFrame(rows, "contig string, allele_id long, pos long, ref_len long, class string").coalesce(1)
    inc = spark.createDataFrame([(a, h) for a in range(8) for h in range(70) if r.random() < 0.3] + [(0, 0), (0, 0)], "allele_id long, hap_id long").coalesce(1)
    segs, haps = cut(backbone.segments(alleles, 0, 1000)), spark.range(70).select(F.col("id").alias("hap_id"))
    return cut(walks.build(segs, alleles, inc, haps)), cut(runs.build(segs, alleles, inc, haps)), segs, inc


def same(a, b):
    key = lambda df: sorted(map(repr, df.select(*a.columns).collect()))
    return key(a) == key(b)


@pytest.mark.parametrize("seed", [0, 1, 2, 3])
def test_runs_equal_the_rows_of_all_nodes(spark, seed):
    walk, own, segs, inc = both(spark, seed)
    assert same(walks.numbered(walk).select("path_id", "contig", F.col("seq").cast("long").alias("seq"), "node"), runs.numbered(own))
    assert same(walks.successors(walk), runs.successors(own, segs))
    for pairs in (inc, inc.where("hap_id <> 1 and allele_id <> 2")):
        assert same(walks.verify_dual(pairs, walk), runs.verify_dual(pairs, own))
    for policy in ("min_cost", "list"):
        assert same(walks.edge_index(walk, 70, policy), runs.edge_index(own, segs, 70, policy))
    for allele in (0, 3, 7):
        assert same(walks.neighborhood(walk, allele, 2), runs.neighborhood(own, segs, allele, 2).withColumn("offset", F.col("offset").cast("int")))
        assert same(walks.neighborhood(walk, allele, 150, "bp"), runs.neighborhood(own, segs, allele, 150, "bp"))
    for lo, hi in ((0, 300), (100, 101), (200, 2000)):
        assert same(walks.local_haplotypes(walk, lo, hi, "c1"), runs.local_haplotypes(own, segs, lo, hi, "c1"))


@pytest.fixture(scope="module")
def lines(spark, tmp_path_factory):
    """60 parts, half of them structural, that 300 suppliers carry now and then: 600 walks of some 60 nodes."""
    at, r = str(tmp_path_factory.mktemp("lines")), random.Random(5)
    write = lambda name, rows, schema: spark.createDataFrame(rows, schema).write.parquet(f"{at}/{name}.parquet")
    write("part", [(i, 49 + i % 4 // 2 if i % 2 else 7, "b", "n", "t") for i in range(60)], "p_partkey long, p_size int, p_brand string, p_name string, p_type string")
    for name, x in (("supplier", "s"), ("customer", "c")):
        write(name, [(i,) for i in range(300)], f"{x}_{'supp' if x == 's' else 'cust'}key long")
    write("orders", [(i, i) for i in range(300)], "o_orderkey long, o_custkey long")
    write("lineitem", [(i % 300, r.randrange(60), r.randrange(300), r.choice("OF")) for i in range(700)], "l_orderkey long, l_partkey long, l_suppkey long, l_linestatus string")
    return at


def moved(spark, run):
    """Rows that all stages of ``run`` wrote to shuffles."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def total():
        found = store.stageList(None, *(getattr(store, f"stageList$default${i}")() for i in (2, 3, 4, 5)))
        return {found.apply(i).stageId(): found.apply(i).shuffleWriteRecords() for i in range(found.size())}

    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    before = total()
    out = run()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    return out, sum(n for stage, n in total().items() if stage not in before)


WALKS = ["dual_violations", "dual_violations_customer", "neighborhood", "neighborhood_bp", "edge_index", "successors", "successors_two_contigs", "local_haplotypes", "walk_nodes", "walk_two_contigs", "node_index"]


@pytest.mark.parametrize("name", WALKS)
def test_no_query_moves_all_nodes(spark, lines, name):
    out, rows = moved(spark, lambda: __spark_entry__.queries()[name](spark, lines).collect())
    assert out and rows < 15_000  # the walks have some 36,000 nodes
