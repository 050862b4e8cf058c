import random
from collections import Counter

from pyspark.sql import functions as F

from carrierpath.operators import backbone, walks
from carrierpath.plans.session import cut


def catalogue(spark, rows):
    return spark.createDataFrame(rows, "contig string, allele_id long, pos long, ref_len long, class string")


def test_worked_segments(spark):
    alleles = catalogue(spark, [("c", 1, 2000, 500, "SV"), ("c", 2, 7000, 0, "SV")])
    segs = backbone.segments(alleles, 0, 10_000)
    assert [(r["start"], r["end"]) for r in segs.orderBy("seg_no").collect()] == [(0, 2000), (2000, 2500), (2500, 7000), (7000, 10_000)]
    assert backbone.segments(alleles, 0, 10_000, "tiled").count() == 11
    found = {r["allele_id"]: (r["before_seg"], r["first_seg"], r["after_seg"]) for r in backbone.bubbles(segs, alleles).collect()}
    assert found == {1: (0, 1, 2), 2: (2, None, 3)}
    fine = backbone.segments(alleles, 0, 10_000, "tiled")
    assert [r["start"] for r in backbone.compact(fine, backbone.cuts(alleles, 0, 10_000)).orderBy("start").collect()] == [0, 2000, 2500, 7000]


def test_published_graph_sizes(spark):
    """45 structural variants in 2 Mb: 91 segments and 90 links; 2,090 segments with tiles of 1 kb."""
    alleles = catalogue(spark, [("c", i, 40_000 * i + 137, 333, "SV") for i in range(1, 46)] + [("c", 1000 + i, 7919 * i % 2_000_000, 1, "SNV") for i in range(200)])
    segs = backbone.segments(alleles, 0, 2_000_000)
    nodes, edges = backbone.graph(segs, alleles)
    size = {r["item"]: r["n"] for r in backbone.size(nodes, edges).collect()}
    assert (size["ref_nodes"], size["ref_edges"], size["alt_nodes"]) == (91, 90, 45)
    assert backbone.segments(alleles, 0, 2_000_000, "tiled").count() == 2090
    assert backbone.annotate(segs, alleles.where("class = 'SNV'")).count() == 200


def test_walks_are_dual_to_rows(spark):
    alleles = catalogue(spark, [("c", 1, 2000, 500, "SV"), ("c", 2, 7000, 0, "SV"), ("c", 3, 8000, 100, "SV")])
    inc = spark.createDataFrame([(1, 0), (1, 2), (2, 2), (3, 1)], "allele_id long, hap_id long")
    haps = spark.range(4).select(F.col("id").alias("hap_id"))
    walk = walks.build(backbone.segments(alleles, 0, 10_000), alleles, inc, haps).cache()
    assert walks.verify_dual(inc, walk).count() == 0
    assert {tuple(r) for r in walks.to_incidence(walk).collect()} == {(1, 0), (1, 2), (2, 2), (3, 1)}
    path = [r["node"] for r in walks.path_of(walk, [2]).orderBy("seq").collect()]
    assert path == ["R0", "A1", "R2", "A2", "R3", "R4", "R5"]
    near = {(r["offset"], r["node"]) for r in walks.neighborhood(walk, 2, 1).collect()}
    assert near == {(-1, "R2"), (0, "A2"), (1, "R3")}
    broken = inc.where("hap_id <> 1")
    assert walks.verify_dual(broken, walk).count() == 1


def test_overlaps_keep_the_earlier(spark):
    alleles = catalogue(spark, [("c", 1, 100, 50, "SV"), ("c", 2, 120, 10, "SV"), ("c", 3, 150, 10, "SV")])
    inc = spark.createDataFrame([(1, 0), (2, 0), (3, 0), (2, 1)], "allele_id long, hap_id long")
    won, lost = walks.resolve_overlaps(alleles, inc)
    assert {tuple(r) for r in won.collect()} == {(1, 0), (3, 0), (2, 1)} and {tuple(r) for r in lost.collect()} == {(2, 0)}


def test_two_contigs_keep_their_own_segments(spark):
    """An alternative on one contig leaves the other contig's segments alone, though positions and counts are the same."""
    alleles = catalogue(spark, [("c1", 1, 2000, 500, "SV"), ("c2", 2, 2000, 500, "SV"), ("c2", 3, 7000, 0, "SV")])
    segs = backbone.segments(alleles, 0, 10_000)
    assert [(r["contig"], r["seg_no"]) for r in segs.orderBy("seg_no").collect()] == [("c1", 0), ("c1", 1), ("c1", 2), ("c2", 3), ("c2", 4), ("c2", 5), ("c2", 6)]
    found = {r["allele_id"]: (r["before_seg"], r["first_seg"], r["after_seg"]) for r in backbone.bubbles(segs, alleles).collect()}
    assert found == {1: (0, 1, 2), 2: (3, 4, 5), 3: (5, None, 6)}
    inc = spark.createDataFrame([(1, 0), (2, 1), (3, 1)], "allele_id long, hap_id long")
    walk = walks.build(segs, alleles, inc, spark.range(2).select(F.col("id").alias("hap_id")))
    path = lambda i: [r["node"] for r in walks.path_of(walk, [i]).orderBy("seq").collect()]
    assert path(0) == ["R0", "A1", "R2", "R3", "R4", "R5", "R6"] and path(1) == ["R0", "R1", "R2", "R3", "A2", "R5", "A3", "R6"]
    assert ("R2", "R3") not in {(r["src"], r["dst"]) for r in walks.edges_of(walk).collect()}
    assert walks.verify_dual(inc, walk).count() == 0
    assert [r["seg_no"] for r in backbone.compact(backbone.segments(alleles, 0, 10_000, "tiled"), backbone.cuts(alleles, 0, 10_000)).orderBy("contig", "start").collect()] == list(range(7))


def test_variant_beyond_the_region(spark):
    alleles = catalogue(spark, [("c", 1, 9000, 5000, "SV")])
    inc = spark.createDataFrame([(1, 0)], "allele_id long, hap_id long")
    walk = walks.build(backbone.segments(alleles, 0, 10_000), alleles, inc, spark.range(1).select(F.col("id").alias("hap_id")))
    assert [r["node"] for r in walks.path_of(walk, [0]).orderBy("seq").collect()] == ["R0", "A1"]


def test_step_counts_equal_those_of_the_walks(spark):
    """Overlaps, insertions, variants beyond the region, two at one place, whole contigs replaced, several contigs."""
    r = random.Random(7)
    for case in range(4):
        contigs = ["c1", "c2"][: 1 + case % 2]
        rows = [(r.choice(contigs), i, r.choice([-50, 0, 100, 200, 300, 300, 400, 950, 1000, 1200]), r.choice([0, 0, 50, 100, 250, 1000]), "SV") for i in range(8)]
        rows += [(c, 90 + i, 10 * i, 1, "SNV") for i, c in enumerate(contigs)]
        alleles = catalogue(spark, rows).coalesce(1)
        inc = spark.createDataFrame([(a, h) for a in range(8) for h in range(9) if r.random() < 0.3] + [(0, 0), (0, 0)], "allele_id long, hap_id long").coalesce(1)
        segs = cut(backbone.segments(alleles, 0, 1000))
        walk = walks.build(segs, alleles, inc, spark.range(9).select(F.col("id").alias("hap_id")))
        labels = walk.groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("contig", "at", "node"))).alias("s")).select("path_id", F.col("s.node").alias("labels"))
        want = Counter()
        for row in labels.collect():
            want.update(zip([None, *row["labels"]], [*row["labels"], None], strict=True))
        got = {(x["src"], x["dst"]): x["n"] for x in walks.step_counts(segs, alleles, inc, 9).collect()}
        assert got == dict(want)
