"""The registered queries: every method, variant, baseline and measure over the given tables."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import backbone, baselines, codec, cost, diag, incidence, markov, normalize, ops, prefix, rows, runs, shards, walks
from ..sources import fixtures as fx
from ..sources.tables import table
from ..streaming import streams
from . import surface
from .session import cut

Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, Query] = {}


def query(name: str):
    def add(f):
        REGISTRY[name] = f
        return f

    return add


def _add(name: str, f: Query) -> None:
    REGISTRY[name] = f


#: Incidence fixtures whose rows are compared one by one.
ROW_FIXTURES = ("supplier", "customer", "events", "embeddings")
#: Alleles that the point queries ask for.
A, B = 0, 1


def pairs(s, d, name):
    fixture = fx.INCIDENCES[name](s, d)
    return incidence.from_calls(fixture.pairs, keep=("class",)), fixture.h


def costs(s, d, name, policy="min_cost"):
    inc, h = pairs(s, d, name)
    return cost.per_row(inc.groupBy("allele_id", "class").agg(F.count(F.lit(1)).alias("k")), h, policy), h


# Incidence and rows -------------------------------------------------------------------------

for _name in (*ROW_FIXTURES, "customer_unphased", "tokens", "benchmark"):
    _add(f"inc_{_name}", lambda s, d, n=_name: pairs(s, d, n)[0].select("allele_id", "hap_id"))
for _name in (*ROW_FIXTURES, "tokens"):
    _add(f"rows_cost_{_name}", lambda s, d, n=_name: costs(s, d, n)[0].drop("class"))
    _add(f"compression_by_class_{_name}", lambda s, d, n=_name: cost.by_class(costs(s, d, n)[0]))
for _name in ("supplier", "events", "embeddings"):
    _add(f"rows_roundtrip_{_name}", lambda s, d, n=_name: rows.decode(rows.encode(*pairs(s, d, n))))


for _name in ("supplier", "customer"):
    _add(f"varint_roundtrip_{_name}", lambda s, d, n=_name: rows.decode_varint(rows.encode_varint(*pairs(s, d, n))))


@query("varint_rows")
def _(s, d):
    """Stored bytes, read off the rows themselves."""
    got = rows.encode_varint(*pairs(s, d, "customer"))
    return got.select("allele_id", "k", "enc", "bits", F.coalesce(8 * F.length("packed"), F.lit(0)).cast("long").alias("stored"))


@query("inc_multiallelic")
def _(s, d):
    return fx.multiallelic(s, d).select("site_id", F.col("alt_no").cast("long").alias("alt_no"), "hap_id")


@query("inc_multiallelic_split")
def _(s, d):
    return incidence.from_calls(fx.multiallelic(s, d))


@query("inc_multiallelic_collapse")
def _(s, d):
    return incidence.from_calls(fx.multiallelic(s, d), multiallelic="collapse")


@query("inc_window")
def _(s, d):
    inc, _ = pairs(s, d, "supplier")
    calls = inc.join(fx.catalogue(s, d).select("allele_id", "pos"), "allele_id").withColumn("sample_id", F.floor(F.col("hap_id") / 2))
    few = table(s, d, "supplier").where("s_nationkey < 10").select(F.col("s_suppkey").alias("sample_id"))
    return incidence.window(calls, 50_000, 150_000, few).select("allele_id", "hap_id")


@query("rows_threshold_policy")
def _(s, d):
    by_cost, h = costs(s, d, "supplier")
    from ..functions import bitops

    enc = bitops.row_encoding(F.col("k"), h, "threshold")
    return by_cost.select("allele_id", "k", enc.alias("enc_threshold"), (enc != F.col("enc")).alias("differs"))


@query("rows_forced_policies")
def _(s, d):
    parts = [costs(s, d, "supplier", p)[0].agg(F.lit(p).alias("policy"), F.sum("bits_hybrid").cast("long").alias("bits")) for p in ("bitmap", "list", "min_cost", "threshold")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


@query("rows_words")
def _(s, d):
    return rows.long_words(pairs(s, d, "supplier")[0])


@query("rows_chunks")
def _(s, d):
    return rows.to_chunks(pairs(s, d, "customer")[0]).select("allele_id", "chunk", F.bitmap_count("bitmap").alias("popcount"))


@query("rows_overhead")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return cost.by_class(cost.per_row(inc.groupBy("allele_id", "class").agg(F.count(F.lit(1)).alias("k")), h, overhead_bits=8))


@query("rows_export")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return rows.export_relation(rows.encode(inc, h).select("allele_id", "class", "k", "enc"), drop=("class",), salt="pepper")


@query("sparsity_by_class")
def _(s, d):
    by_cost, h = costs(s, d, "tokens")
    return ops.rarity(by_cost, h)


@query("sparsity_by_class_customer")
def _(s, d):
    by_cost, h = costs(s, d, "customer")
    return ops.rarity(by_cost, h)


@query("af_spectrum")
def _(s, d):
    by_cost, h = costs(s, d, "supplier")
    return ops.spectrum(by_cost, h)


@query("k_histogram")
def _(s, d):
    return costs(s, d, "tokens")[0].groupBy("k").agg(F.count(F.lit(1)).alias("n_rows"))


@query("merge_additivity")
def _(s, d):
    inc, h = pairs(s, d, "customer")
    snv, sv = (rows.encode(inc.where(F.col("class") == c), h) for c in ("SNV", "SV"))
    merged = rows.merge(snv, sv).select("allele_id", F.lit("merged").alias("class"), "k", "bits")
    each = snv.unionByName(sv).select("allele_id", "class", "k", "bits").unionByName(merged)
    return each.groupBy("class").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("bits").cast("long").alias("bits"))


def _envelope(s, d, name):
    by_cost, h = costs(s, d, name)
    real, whole = cost.break_even(h)
    mean = lambda c: F.round(F.avg(c), 6)
    return by_cost.groupBy("k").agg(
        F.count(F.lit(1)).alias("n_rows"), mean("bits_dense").alias("cost_bitmap"), mean("bits_list").alias("cost_list"), mean("bits_hybrid").alias("cost_hybrid"),
        F.lit(round(real, 6)).alias("k_real"), F.lit(whole).cast("long").alias("k_int"),
    )


_add("lower_envelope", lambda s, d: _envelope(s, d, "supplier"))
for _name in ("customer", "customer_unphased", "tokens", "events", "embeddings", "benchmark"):
    _add(f"lower_envelope_{_name}", lambda s, d, n=_name: _envelope(s, d, n))


@query("break_even_sweep")
def _(s, d):
    from ..functions import bitops

    inc, h = pairs(s, d, "supplier")
    sizes = F.explode(F.array(*[F.lit(x).cast("long") for x in (h, h // 2, h // 4, h // 5) if x > 1])).alias("h")
    own = inc.select("allele_id", "hap_id", sizes).where("hap_id < h").groupBy("h", "allele_id").agg(F.count(F.lit(1)).alias("k"))
    width = bitops.id_width_of(F.col("h"))
    total = lambda c: F.sum(c).cast("long")
    out = own.groupBy("h").agg(F.count(F.lit(1)).alias("n_rows"), total("h").alias("bits_bitmap"), total(F.col("k") * width).alias("bits_list"), total(F.least("h", F.col("k") * width)).alias("bits_hybrid"))
    return out.withColumn("k_real", F.round(F.col("h") / F.log2(F.col("h").cast("double")), 6)).withColumn("k_int", F.floor(F.col("h") / width))


@query("delta_varint_cost")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return cost.delta_varint(inc, h)


@query("container_cost")
def _(s, d):
    inc, h = pairs(s, d, "customer")
    return cost.container_bitmap(inc, h)


# Set queries ----------------------------------------------------------------------------------


def _rows(s, d, name="supplier", policy="min_cost"):
    inc, h = pairs(s, d, name)
    return rows.encode(inc, h, policy), inc, h


@query("carriers_of")
def _(s, d):
    return ops.carriers(_rows(s, d)[0], [A, B, 5])


@query("allele_frequency")
def _(s, d):
    enc, _, h = _rows(s, d)
    return ops.frequency(enc, h).withColumn("af", F.round("af", 6))


@query("allele_frequency_popcount")
def _(s, d):
    enc, _, h = _rows(s, d, policy="bitmap")
    return ops.frequency_by_popcount(enc, h).withColumn("af", F.round("af", 6))


@query("site_major_carriers")
def _(s, d):
    return baselines.carriers_scan(baselines.site_major(fx.multiallelic(s, d)), A, 2)


@query("site_major_frequency")
def _(s, d):
    h = fx.supplier(s, d).h
    return baselines.frequency_scan(baselines.site_major(fx.multiallelic(s, d)), h).select("site_id", F.col("alt_no").cast("long").alias("alt_no"), "k", F.round("af", 6).alias("af"))


@query("haplotype_major_burden")
def _(s, d):
    return baselines.haplotype_major(pairs(s, d, "supplier")[0]).select("hap_id", F.size("alleles").cast("long").alias("n"))


@query("haplotype_major_carriers")
def _(s, d):
    return baselines.carriers_by_haplotype_scan(baselines.haplotype_major(pairs(s, d, "supplier")[0]), A)


@query("burden_rare")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return ops.burden(inc, ops.rare(incidence.counts(inc), h, max_af=0.1))


for _how in ("merge", "and", "probe", "auto"):
    _add(f"intersect_{_how}", lambda s, d, how=_how: (lambda r: ops.intersect(r[0], A, B, r[2], how).select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"), "hap_id"))(_rows(s, d)))


@query("intersect_cost")
def _(s, d):
    enc, _, h = _rows(s, d)
    return ops.touched(enc, A, B, h)


for _how in ("union", "difference", "complement"):
    _add(f"carriers_{_how}", lambda s, d, how=_how: (lambda p: ops.combine(p[0], [A, B], how, p[1]))(pairs(s, d, "supplier")))


@query("cohort_filter")
def _(s, d):
    return ops.cohort_filter(_rows(s, d, "events")[0], require=["click:1", "view:2"])


@query("cohort_filter_stepwise")
def _(s, d):
    return ops.cohort_filter(_rows(s, d)[0], require=[A, B], early_stop=True)


@query("cohort_filter_exclude")
def _(s, d):
    return ops.cohort_filter(_rows(s, d)[0], require=[A], exclude=[B, 2])


@query("cohort_exclude_only")
def _(s, d):
    enc, _, h = _rows(s, d)
    return ops.cohort_filter(enc, exclude=[A, B], h=h)


@query("cohort_repeated_names")
def _(s, d):
    return ops.cohort_filter(_rows(s, d)[0], require=[A, B, A])


@query("cohort_any_of")
def _(s, d):
    return ops.cohort_filter(_rows(s, d)[0], any_of=[A, B, 2], exclude=[3])


@query("cohort_words")
def _(s, d):
    return ops.cohort_filter(rows.encode(*pairs(s, d, "tokens")), require=["the", "and"], exclude=["with"])


@query("co_carriage")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return ops.co_carriage(inc, ops.rare(incidence.counts(inc), h, max_k=20))


def _supplier_cohort(s, d):
    nation = table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("s_nationkey"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
    own = table(s, d, "supplier").join(F.broadcast(nation), "s_nationkey")  # a row per nation
    return own.select(F.explode(F.array(2 * F.col("s_suppkey"), 2 * F.col("s_suppkey") + 1)).alias("hap_id"), "nation", "region")


@query("stratify_nation")
def _(s, d):
    return ops.stratify(pairs(s, d, "supplier")[0], _supplier_cohort(s, d), "nation").withColumn("af", F.round("af", 6))


@query("stratify_rollup")
def _(s, d):
    return pairs(s, d, "supplier")[0].join(_supplier_cohort(s, d), "hap_id").rollup("region", "nation").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("allele_id").alias("alleles"))


@query("stratify_cube")
def _(s, d):
    return pairs(s, d, "supplier")[0].join(_supplier_cohort(s, d), "hap_id").cube("class", "region").agg(F.count(F.lit(1)).alias("n"))


@query("private_alleles")
def _(s, d):
    inc, _ = pairs(s, d, "tokens")
    return ops.private(inc, table(s, d, "documents").select(F.col("doc_id").alias("hap_id"), "lang"), "lang")


@query("rare_alleles")
def _(s, d):
    by_cost, h = costs(s, d, "supplier")
    return ops.rare(by_cost, h, max_af=0.1, max_k=18).select("allele_id", "class", "k")


@query("topk_frequent")
def _(s, d):
    return costs(s, d, "tokens")[0].select("allele_id", "k").orderBy(F.desc("k"), "allele_id").limit(20)


@query("k_quantiles")
def _(s, d):
    return costs(s, d, "supplier")[0].groupBy("class").agg(*[F.round(F.percentile("k", q), 6).alias(f"p{int(q * 100)}") for q in (0.25, 0.5, 0.9)])


@query("phenotype_tokens")
def _(s, d):
    inc, h = pairs(s, d, "benchmark")
    cohort = table(s, d, "documents").select(F.col("doc_id").alias("hap_id")).join(table(s, d, "labels").select(F.col("doc_id").alias("hap_id"), F.col("toxic").cast("string").alias("toxic")), "hap_id", "left")
    return ops.stratify(inc, cohort.withColumn("toxic", F.coalesce("toxic", F.lit("none"))), "toxic").withColumn("af", F.round("af", 6))


# Graph views ----------------------------------------------------------------------------------


def _graph(s, d, mode="sv", kind="plain", tile=1000):
    lo, hi = fx.region(s, d)
    alleles = fx.catalogue(s, d, kind)
    return backbone.segments(alleles, lo, hi, mode, tile), alleles


def _segs(s, d, **k):
    return _graph(s, d, **k)[0].select(F.col("seg_no").cast("long").alias("seg_no"), "start", "end")


_add("segments_sv", lambda s, d: _segs(s, d))
_add("segments_tiled", lambda s, d: _segs(s, d, mode="tiled"))
_add("segments_every_variant", lambda s, d: _segs(s, d, mode="every_variant"))
_add("segments_insertions", lambda s, d: _segs(s, d, kind="insertions"))


@query("segments_compacted")
def _(s, d):
    fine, alleles = _graph(s, d, "every_variant")
    lo, hi = fx.region(s, d)
    return backbone.compact(fine, backbone.cuts(alleles, lo, hi, "sv")).select(F.col("seg_no").cast("long").alias("seg_no"), "start", "end")


@query("tile_sweep")
def _(s, d):
    out = None
    for tile in (250, 500, 1000, 5000, 10000):
        one = _graph(s, d, "tiled", tile=tile)[0].agg(F.lit(tile).cast("long").alias("tile"), F.count(F.lit(1)).alias("segments"))
        out = one if out is None else out.unionByName(one)
    return out


@query("bubbles")
def _(s, d):
    return backbone.bubbles(*_graph(s, d)).select("allele_id", *(F.col(c).cast("long").alias(c) for c in ("before_seg", "first_seg", "after_seg")))


@query("snv_annotations")
def _(s, d):
    segs, alleles = _graph(s, d)
    return backbone.annotate(segs, alleles.where("class = 'SNV'")).select("allele_id", F.col("seg_no").cast("long").alias("seg_no"))


@query("side_nodes")
def _(s, d):
    segs, alleles = _graph(s, d, "tiled")
    return backbone.annotate(segs, alleles.where("class = 'SNV'")).groupBy(F.col("seg_no").cast("long").alias("seg_no")).agg(F.count(F.lit(1)).alias("n"))


@query("graph_size")
def _(s, d):
    return backbone.size(*backbone.graph(*_graph(s, d))).withColumn("mode", F.lit("sv")).unionByName(backbone.size(*backbone.graph(*_graph(s, d, "tiled"), side_nodes=True)).withColumn("mode", F.lit("tiled")))


@query("graph_select")
def _(s, d):
    alleles = backbone.select(fx.catalogue(s, d), 10, 3)
    lo, hi = fx.region(s, d)
    return backbone.size(*backbone.graph(backbone.segments(alleles, lo, hi, "tiled"), alleles, side_nodes=True))


@query("gfa_lines")
def _(s, d):
    return backbone.exchange_lines(*backbone.graph(*_graph(s, d)))


# Walks ----------------------------------------------------------------------------------------


def _walk_inc(s, d, name):
    """Structural variants and their carriers, as ids of the catalogue."""
    fixture = fx.customer(s, d, "SV") if name == "customer" else fx.INCIDENCES[name](s, d)
    inc, h = incidence.from_calls(fixture.pairs.where("class = 'SV'")), fixture.h  # an allele has one class, so others need no shuffle
    own = F.col("allele_id") if name == "supplier" else F.substring("allele_id", 3, 20).try_cast("long").alias("allele_id")
    return inc.select(own, "hap_id"), h


def _walk(s, d, name="supplier"):
    segs, alleles = _graph(s, d)
    inc, h = _walk_inc(s, d, name)
    return walks.build(segs, alleles, inc, s.range(h).select(F.col("id").alias("hap_id"))), inc, h


def _runs(s, d, name="supplier", graph=_graph):
    """The same walks as runs, the segments, pairs and cohort size."""
    segs, alleles = graph(s, d)
    segs = cut(segs)
    inc, h = _walk_inc(s, d, name)
    return runs.build(segs, alleles, inc, s.range(h).select(F.col("id").alias("hap_id"))), segs, inc, h


@query("walk_nodes")
def _(s, d):
    return runs.numbered(_runs(s, d)[0]).select("path_id", "seq", "node")


@query("walk_site_lists")
def _(s, d):
    _, inc, _ = _walk(s, d)
    return walks.site_lists(inc, fx.catalogue(s, d)).select("path_id", F.array_join(F.transform("alleles", lambda x: x.cast("string")), ",").alias("alleles"))


@query("edge_index")
def _(s, d):
    own, segs, _, h = _runs(s, d)
    return runs.edge_index(cut(own), segs, h).select(F.col("allele_id").alias("edge"), "k", "enc", "bits")


@query("dual_violations")
def _(s, d):
    own, _, inc, _ = _runs(s, d)
    return runs.verify_dual(inc, own).agg(F.count(F.lit(1)).alias("violations"))


@query("dual_violations_customer")
def _(s, d):
    own, _, inc, _ = _runs(s, d, "customer")
    return runs.verify_dual(inc, own).agg(F.count(F.lit(1)).alias("violations"))


@query("walk_to_incidence")
def _(s, d):
    return walks.to_incidence(_walk(s, d)[0])


@query("path_of")
def _(s, d):
    return walks.path_of(_walk(s, d)[0], [0, 7]).select("path_id", F.col("seq").cast("long").alias("seq"), "node")


def _rarest(s, d, inc):
    return inc.groupBy("allele_id").agg(F.count(F.lit(1)).alias("k")).orderBy("k", "allele_id").first()["allele_id"]


@query("neighborhood")
def _(s, d):
    own, segs, inc, _ = _runs(s, d)
    return runs.neighborhood(cut(own), segs, _rarest(s, d, inc), 2).select("path_id", F.col("offset").cast("long").alias("offset"), "node")


@query("neighborhood_bp")
def _(s, d):
    own, segs, inc, _ = _runs(s, d)
    return runs.neighborhood(cut(own), segs, _rarest(s, d, inc), 60_000, "bp").select("path_id", F.col("offset").cast("long").alias("offset"), "node")


@query("successors")
def _(s, d):
    own, segs, _, _ = _runs(s, d)
    return runs.successors(cut(own), segs)


@query("before_after")
def _(s, d):
    walk, inc, _ = _walk(s, d)
    return walks.before(walk, f"A{_rarest(s, d, inc)}", "R10")


@query("local_haplotypes")
def _(s, d):
    lo, hi = fx.region(s, d)
    own, segs, _, _ = _runs(s, d)
    return runs.local_haplotypes(own, segs, lo, hi // 10)


@query("carriers_by_walk")
def _(s, d):
    walk, inc, _ = _walk(s, d)
    return baselines.carriers_by_walk(walk, f"A{_rarest(s, d, inc)}")


def _two_contigs(s, d):
    """The catalogue dealt to two contigs by the parity of the allele, so that both have the same positions."""
    alleles = fx.catalogue(s, d).withColumn("contig", F.concat(F.lit("c"), (F.col("allele_id") % 2).cast("string")))
    return backbone.segments(alleles, *fx.region(s, d)), alleles


@query("segments_two_contigs")
def _(s, d):
    return _two_contigs(s, d)[0]


@query("graph_size_two_contigs")
def _(s, d):
    nodes, edges = backbone.graph(*_two_contigs(s, d))
    return backbone.size(nodes, edges).unionByName(nodes.agg(F.countDistinct("node").alias("n")).withColumn("item", F.lit("names")))


@query("walk_two_contigs")
def _(s, d):
    return runs.numbered(_runs(s, d, graph=_two_contigs)[0]).select("path_id", "contig", "seq", "node")


@query("successors_two_contigs")
def _(s, d):
    own, segs, _, _ = _runs(s, d, graph=_two_contigs)
    return runs.successors(cut(own), segs)


@query("overlap_conflicts")
def _(s, d):
    inc, _ = pairs(s, d, "supplier")
    won, lost = walks.resolve_overlaps(fx.catalogue(s, d, "overlapping"), inc.select("allele_id", "hap_id"))
    return won.withColumn("kept", F.lit(True)).unionByName(lost.withColumn("kept", F.lit(False)))


@query("prefix_sorted_runs")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return baselines.prefix_sorted_runs(inc, fx.catalogue(s, d), h)


@query("comparison_matrix")
def _(s, d):
    inc, h = pairs(s, d, "supplier")
    return baselines.measured(incidence.counts(inc), h, A)


# Paths and the coder ----------------------------------------------------------------------------


def _alternatives(segs, alleles):
    """(allele_id, name): alternatives named by the first segment that they replace."""
    return backbone.bubbles(segs, alleles).select("allele_id", F.concat(F.lit("A"), F.col("first_seg").cast("string")).alias("name"))


def _walk_labels(s, d, name):
    walk, _, _ = _walk(s, d, name)
    first = _alternatives(*_graph(s, d)).withColumnRenamed("name", "alt")
    return walk.join(first, "allele_id", "left").select("path_id", F.struct("at").alias("at"), F.coalesce("alt", "node").alias("label"))


STEPS: dict[str, Query] = {
    "events": fx.event_paths, "roles": fx.role_paths, "brands": fx.brand_paths, "tags": fx.tag_paths, "words": fx.word_paths,
    "words_short": lambda s, d: fx.word_paths(s, d, 400), "walk_supplier": lambda s, d: _walk_labels(s, d, "supplier"), "walk_customer": lambda s, d: _walk_labels(s, d, "customer"),
}
#: Path fixtures whose codes SQL builds too ("words_short" is no more than a sample for that), and the words of all documents.
CODED = ("events", "roles", "brands", "walk_supplier", "words_short", "words")


def _steps(s, d, name):
    return STEPS[name](s, d)


def _index(s, d, name):
    if name in COUNTED:  # the labels of its steps, without any path
        return normalize.node_index(COUNTED[name](s, d).where("dst is not null").select(F.col("dst").alias("label")))
    return normalize.node_index(_steps(s, d, name))


#: Largest label index that is sent to every task; a larger one is joined by a shuffle, of which frequent labels are split at run time.
INDEX_ROWS = 500_000


def _paths(s, d, name):
    """(path_id, nodes) and the label index."""
    steps = _steps(s, d, name)
    index = cut(normalize.node_index(steps))
    own = steps.join(F.broadcast(index) if index.limit(INDEX_ROWS + 1).count() <= INDEX_ROWS else index, "label").groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("at", "idx"))).alias("s"))
    return own.select("path_id", F.transform("s", lambda x: x["idx"]).alias("nodes")), index


def _walk_counts(s, d, name):
    segs, alleles = (cut(x) for x in _graph(s, d))
    inc, h = _walk_inc(s, d, name)
    return walks.step_counts(segs, alleles, inc, h, _alternatives(segs, alleles))


#: Path fixtures whose paths are whole in a row, or whose steps are counted without any path.
IN_ROW: dict[str, Query] = {"words": fx.word_arrays, "words_short": lambda s, d: fx.word_arrays(s, d, 400), "tags": fx.tag_arrays}
COUNTED: dict[str, Query] = {f"walk_{n}": lambda s, d, n=n: _walk_counts(s, d, n) for n in ("supplier", "customer")}


def _counts(s, d, name):
    return _numbered_counts(s, d, name)[0]


def _numbered_counts(s, d, name):
    """(ctx, sym, n) and the label index: transitions are counted by their labels and numbered after, so no step is joined with the index."""
    if name in COUNTED:
        counted = COUNTED[name](s, d)
    else:
        counted = markov.count_labels(IN_ROW[name](s, d) if name in IN_ROW else fx.arrays(_steps(s, d, name)))
    counted = cut(counted)
    index = cut(normalize.node_index(counted.where("dst is not null").select(F.col("dst").alias("label"))))
    return markov.number(counted, _sent(index)), index


def _sent(index):
    return F.broadcast(index) if index.limit(INDEX_ROWS + 1).count() <= INDEX_ROWS else index


def _walk_book(s, d, name):
    """Walks as runs in a row, the numbers of the segments, the codebook and the label index; no row has all nodes of a walk."""
    counts, index = _numbered_counts(s, d, name)
    segs, alleles = (cut(x) for x in _graph(s, d))
    inc, h = _walk_inc(s, d, name.removeprefix("walk_"))
    own = runs.build(segs, alleles, inc, s.range(h).select(F.col("id").alias("hap_id")), _alternatives(segs, alleles))
    return cut(runs.by_path(own, _sent(index))), runs.spine(segs, index), cut(codec.fit_counts(counts)), index


def _book(s, d, name, alpha=1.0, force_stop=True, escape="off", cache="profile", single="empty"):
    return codec.fit_counts(_counts(s, d, name), alpha, force_stop, escape, cache, single)


_add("node_index", lambda s, d: _index(s, d, "walk_supplier"))
_add("node_index_words", lambda s, d: _index(s, d, "words"))


@query("adjacency")
def _(s, d):
    counts = _counts(s, d, "walk_supplier").where("ctx >= 0 and sym >= 0")
    return normalize.adjacency(counts.select(F.col("ctx").alias("src"), F.col("sym").alias("dst"))).select("src", F.array_join(F.transform("dsts", lambda x: x.cast("string")), ",").alias("dsts"))


#: Largest edge map that is sent to every task; with a larger one the steps of walks are joined with it.
EDGE_ROWS = 1_000_000


@query("edge_expand")
def _(s, d):
    from pyspark.sql import Window

    runs_, segs, _, _ = _runs(s, d)
    runs_ = cut(runs_)
    edges = normalize.node_index(runs.successors(runs_, segs).select(F.struct("src", "dst").alias("label"))).select("label.src", "label.dst", (F.col("idx") + 1).alias("edge_id"))
    edges = cut(edges)
    if edges.limit(EDGE_ROWS + 1).count() <= EDGE_ROWS:
        index = cut(normalize.node_index(edges.select(F.explode(F.array("src", "dst")).alias("label"))))
        got = codec.expand_by_row(runs.by_path(runs_, _sent(index)), edges, index, runs.spine(segs, index))
        return got.select("path_id", "labels", "ok")
    w = Window.partitionBy("path_id").orderBy("seq")
    own = runs.numbered(runs_).select("path_id", F.col("seq").alias("at"), F.col("node").alias("src"), F.lead("node").over(w).alias("dst")).where("dst is not null").join(edges, ["src", "dst"])
    ids = own.groupBy("path_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "edge_id"))), lambda x: x["edge_id"]).alias("edge_ids"))
    return normalize.expand_edges(ids, edges).select("path_id", F.array_join("labels", ",").alias("labels"), "ok")


for _name in ("events", "roles", "brands", "walk_supplier", "walk_customer", "words", "tags"):
    _add(f"transitions_{_name}", lambda s, d, n=_name: _counts(s, d, n))
for _alpha in (0, 1, 10):
    _add(f"weights_alpha{_alpha}", lambda s, d, a=_alpha: markov.weights(_counts(s, d, "events"), a, force_stop=False))
_add("weights_force_stop", lambda s, d: markov.weights(_counts(s, d, "walk_supplier")))
_add("weights_escape", lambda s, d: markov.weights(_counts(s, d, "events"), escape="reserved"))
_add("weights_stop_twice", lambda s, d: markov.weights(_counts(s, d, "roles"), stop_smoothing="double"))


def _encoded(s, d, name, block=None):
    """(encoded walks, codebook), as blocks of ``block`` symbols if it is given."""
    if name in COUNTED:
        own, spine, book, _ = _walk_book(s, d, name)
        return codec.encode_by_row(own, book, spine) if block is None else codec.encode_blocks_by_row(own, book, block, spine), book
    paths = cut(_paths(s, d, name)[0])
    book = cut(codec.fit(paths))
    return codec.encode(paths, book) if block is None else codec.encode_blocks(paths, book, block), book


for _name in CODED:
    _add(f"code_lengths_{_name}", lambda s, d, n=_name: _book(s, d, n).select("ctx", "sym", F.col("len").cast("long").alias("len")))
    _add(f"context_diagnostics_{_name}", lambda s, d, n=_name: diag.contexts(_book(s, d, n)).select("ctx", "events", "alphabet", *(F.round(c, 6).alias(c) for c in ("h", "l", "gap"))))
    _add(f"global_diagnostics_{_name}", lambda s, d, n=_name: diag.global_(cut(_book(s, d, n))))
    _add(f"encode_{_name}", lambda s, d, n=_name: _encoded(s, d, n)[0].select("path_id", "n_symbols", "n_bits", "status"))
    _add(f"coder_comparison_{_name}", lambda s, d, n=_name: diag.comparison(cut(_book(s, d, n))))
for _name in ("events", "roles", "brands", "walk_supplier"):
    _add(f"canonical_codes_{_name}", lambda s, d, n=_name: _book(s, d, n).select("ctx", "sym", "code"))
for _name in ("walk_customer", "tags"):
    _add(f"global_diagnostics_{_name}", lambda s, d, n=_name: diag.global_(cut(_book(s, d, n))))
    _add(f"coder_comparison_{_name}", lambda s, d, n=_name: diag.comparison(cut(_book(s, d, n))))


def _whole(s, d, name, block=None):
    if name == "words":  # its codebook grows with the text
        return shards.decode(shards.encode(fx.word_texts(s, d), block)).select("path_id", "seq", "node")
    whole = codec.decode_alike if name in COUNTED else codec.decode
    return (whole if block is None else codec.decode_blocks)(*_encoded(s, d, name, block)).select("path_id", "seq", "node")


for _name in ("events", "roles", "walk_supplier", "words_short", "words"):
    _add(f"decode_{_name}", lambda s, d, n=_name: _whole(s, d, n))
    _add(f"decode_blocks_{_name}", lambda s, d, n=_name: _whole(s, d, n, 32))

    def _joined(s, d, n=_name):
        if n in COUNTED:
            own, spine, book, _ = _walk_book(s, d, n)
            return codec.decode_blocks_joined(codec.encode_blocks_by_row(own, book, 32, spine), codec.block_contexts_by_row(own, book, 32, spine), book).select("path_id", "seq", "node")
        paths = cut(_paths(s, d, n)[0])
        book = cut(codec.fit(paths))
        return codec.decode_blocks_joined(codec.encode_blocks(paths, book, 32), codec.block_contexts(paths, 32), book).select("path_id", "seq", "node")

    if _name != "words":  # every block would meet the whole alphabets of common words
        _add(f"decode_blocks_joined_{_name}", _joined)


@query("decode_prefix")
def _(s, d):
    return codec.decode(*_encoded(s, d, "walk_supplier"), first=5).select("path_id", "seq", "node")


@query("decode_trace")
def _(s, d):
    paths = cut(_paths(s, d, "roles")[0])
    book = cut(codec.fit(paths))
    return codec.trace(codec.encode(paths, book), book)


@query("decode_errors")
def _(s, d):
    """Streams cut short, with a wrong context, and with an escape symbol, beside a whole one."""
    paths = cut(_paths(s, d, "events")[0])
    book = cut(codec.fit(paths, escape="reserved"))
    good = codec.encode(paths, book).select("path_id", "bits", "n_bits")
    short = good.select((F.col("path_id") + 1_000_000).alias("path_id"), "bits", F.floor(F.col("n_bits") / 2).alias("n_bits"))
    esc = book.where("ctx = -1 and sym = -3").select(F.lit(2_000_000).cast("long").alias("path_id"), codec.pack_bits("code").alias("bits"), F.length("code").cast("long").alias("n_bits"))
    got = codec.decode(good.unionByName(short).unionByName(esc), book)
    return got.groupBy(F.floor(F.col("path_id") / 1_000_000).alias("kind"), "status").agg(F.countDistinct("path_id").alias("paths"))


@query("round_trip_violations")
def _(s, d):
    paths = cut(_paths(s, d, "brands")[0])
    book = cut(codec.fit(paths))
    return codec.verify(paths, codec.encode(paths, book), book).agg(F.count(F.lit(1)).alias("violations"))


for _suffix, _name in (("", "words_short"), ("_words", "words")):
    _add(f"kraft_check{_suffix}", lambda s, d, n=_name: prefix.verify(_book(s, d, n)).select("ctx", "symbols", "kraft"))


@query("prefix_free_check")
def _(s, d):
    return prefix.verify(_book(s, d, "brands")).agg(F.sum("clashes").cast("long").alias("clashes"))


@query("incremental_model")
def _(s, d):
    paths = cut(_paths(s, d, "events")[0])
    return markov.update(markov.count(paths.where("path_id % 3 <> 0")), markov.count(paths.where("path_id % 3 = 0")))


@query("incremental_refit")
def _(s, d):
    """A book of two thirds of the paths, refitted by the counts of the rest."""
    paths = cut(_paths(s, d, "brands")[0])
    book = cut(codec.fit(paths.where("path_id % 3 <> 0")))
    return codec.refit(book, cut(markov.count(paths.where("path_id % 3 = 0")))).select("ctx", "sym", "code")


@query("incremental_touched")
def _(s, d):
    """Codes that few new paths leave as they are, and codes made again."""
    own, spine, book, _ = _walk_book(s, d, "walk_supplier")
    delta = cut(markov.count(codec.listed(own.where("path_id = 0"), spine)))
    again = book.join(markov.touched(delta), "ctx", "left_semi").select(F.lit("again").alias("part"), "ctx")
    kept = book.join(markov.touched(delta), "ctx", "left_anti").select(F.lit("kept").alias("part"), "ctx")
    return again.unionByName(kept).groupBy("part").agg(F.countDistinct("ctx").alias("contexts"), F.count(F.lit(1)).alias("codes"))


def _linear(s, d, name):
    """Work against size: for growing parts of the paths, the symbols, the steps that are counted and coded, the rows of the model and the bits."""
    paths, out = cut(_paths(s, d, name)[0]), None
    for quarter in (1, 2, 3, 4):
        own = paths.where(F.col("path_id") % 4 < quarter)
        book = cut(prefix.lengths(markov.weights(markov.count(own))))
        total = lambda c: F.sum(c).cast("long")
        one = book.agg(total("n").alias("symbols"), total((F.col("n") > 0).cast("long")).alias("transitions"), F.countDistinct("ctx").alias("contexts"), total(F.col("n") * F.col("len")).alias("payload_bits"))
        one = own.agg(F.count(F.lit(1)).alias("paths"), total(F.size("nodes")).alias("nodes")).crossJoin(F.broadcast(one)).select(F.lit(quarter).cast("long").alias("quarters"), "*")
        out = one if out is None else out.unionByName(one)
    return out


for _name in ("events", "brands"):
    _add(f"cost_linearity_{_name}", lambda s, d, n=_name: _linear(s, d, n))


@query("cost_linearity_seconds")
def _(s, d):
    """Seconds of counting, fitting and encoding the walks of events, and of their first half of paths, as measured; no SQL can have these."""
    paths, made = cut(_paths(s, d, "events")[0]), []
    for part, own in (("half", paths.where("path_id % 2 = 0")), ("all", paths)):
        began = time.time()
        symbols = codec.encode(own, cut(codec.fit(own))).agg(F.sum("n_symbols")).first()[0]
        made.append((part, symbols, time.time() - began))
    return s.createDataFrame(made, "part string, symbols long, seconds double")


# SQL surface --------------------------------------------------------------------------------------


@query("sql_rows")
def _(s, d):
    """Costs and encodings of carrier rows, all said in SQL."""
    inc, h = pairs(s, d, "customer")
    surface.register_functions(s)
    surface.register_views({"carrier_pairs": inc})
    return s.sql(
        f"SELECT allele_id, k, carrier_bits_dense({h}) AS bits_dense, carrier_bits_list(k, {h}) AS bits_list, carrier_bits_hybrid(k, {h}) AS bits_hybrid, carrier_row_encoding(k, {h}) AS enc"
        " FROM (SELECT allele_id, count(*) AS k FROM carrier_pairs GROUP BY allele_id)"
    )


@query("sql_words")
def _(s, d):
    """Set operations on the words of two alleles, all said in SQL."""
    inc, h = pairs(s, d, "supplier")
    surface.register_functions(s)
    surface.register_views({"carrier_words": rows.to_words(inc, h)})
    return s.sql(
        f"SELECT o.allele_id, carrier_popcount(o.words) AS k, carrier_contains(o.words, 3L) AS has_3, carrier_popcount(carrier_and(o.words, a.words)) AS both, carrier_popcount(carrier_or(o.words, a.words)) AS any_of,"
        f" carrier_popcount(carrier_and_not(o.words, a.words)) AS without, array_join(carrier_ids(o.words), ',') AS ids FROM carrier_words o CROSS JOIN (SELECT words FROM carrier_words WHERE allele_id = {A}) a"
    )


@query("sql_trace_decode")
def _(s, d):
    """Every decoding step by a table function, joined laterally."""
    paths = cut(_paths(s, d, "roles")[0])
    book = cut(codec.fit(paths))
    surface.register_trace(s, book)
    surface.register_views({"carrier_walks": codec.encode(paths, book)})
    return s.sql("SELECT w.path_id, t.step, t.ctx, t.code, t.sym, t.bit_offset, t.status FROM carrier_walks w, LATERAL trace_decode(w.bits, w.n_bits) t")


@query("alpha_sweep")
def _(s, d):
    counts, out = cut(_counts(s, d, "events")), None
    for alpha in (0.0, 0.5, 1.0, 10.0):
        for stop in (False, True):
            one = diag.global_(cut(prefix.lengths(markov.weights(counts, alpha, stop)))).select(F.lit(alpha).alias("alpha"), F.lit(stop).alias("force_stop"), "h_global", "l_global", "realized")
            out = one if out is None else out.unionByName(one)
    return out


for _suffix, _name in (("", "words_short"), ("_words", "words")):

    def _swept(s, d, n=_name):
        book, out = cut(_book(s, d, n)), None
        for m in (1, 10, 100):
            one = diag.global_(book, m).select(F.lit(m).cast("long").alias("min_events"), "contexts_kept", "h_global", "l_global")
            out = one if out is None else out.unionByName(one)
        return out

    _add(f"min_events_sweep{_suffix}", _swept)


@query("signature_modes")
def _(s, d):
    counts, out = cut(_counts(s, d, "brands")), None
    for mode in ("profile", "counts", "support", "off"):
        book = cut(prefix.lengths(markov.weights(counts), mode))
        one = diag.global_(book).select(F.lit(mode).alias("mode"), "h_global", "l_global", "realized", "bound_violations").crossJoin(diag.fit_size(book).select("signatures", "reused"))
        out = one if out is None else out.unionByName(one)
    return out


@query("single_symbol_modes")
def _(s, d):
    counts, out = cut(_counts(s, d, "walk_supplier")), None
    for mode in ("empty", "one_bit"):
        one = diag.global_(cut(prefix.lengths(markov.weights(counts, 0.0, False), single_symbol=mode))).select(F.lit(mode).alias("mode"), "h_global", "l_global", "realized")
        out = one if out is None else out.unionByName(one)
    return out


@query("full_alphabet_cost")
def _(s, d):
    return diag.full_alphabet(cut(_book(s, d, "words", force_stop=False)))


@query("fit_size")
def _(s, d):
    return diag.fit_size(_book(s, d, "words"))


@query("ondisk_ratio")
def _(s, d):
    """Bytes of 32-bit symbols, of the coded bits, and of the bits with model and index, as Parquet files in the shared folder."""
    cut(s.range(1))
    folder = f"{s.sparkContext.getCheckpointDir()}/ondisk-{uuid.uuid4().hex}"
    own, spine, book, index = _walk_book(s, d, "walk_customer")
    codec.save(folder, codec.encode_by_row(own, book, spine).select("path_id", "n_symbols", "n_bits", "bits", "status"), book, index)
    symbols = book.agg(F.sum("n")).first()[0]
    bits, model, idx = (codec.bytes_on_disk(s, f"{folder}/{x}") for x in ("bits", "model", "index"))
    whole = bits + model + idx
    return s.createDataFrame([(4 * symbols, bits, model + idx, 4 * symbols / whole)], "raw_bytes long, payload_bytes long, model_bytes long, ratio double")


# Streams ----------------------------------------------------------------------------------------


def _event_files(s, d, change=None):
    """A folder of the event table as four files in time order, each changed by ``change`` if it is given."""
    cut(s.range(1))
    folder = f"{s.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"
    # A replay: the file source takes files by age, so they are written one after another in time order.
    events = table(s, d, "events").withColumn("_at", F.unix_timestamp("ts"))
    bounds = [None, *events.approxQuantile("_at", [0.25, 0.5, 0.75], 0.01), None]
    for lo, hi in zip(bounds, bounds[1:], strict=False):
        part = events if lo is None else events.where(F.col("_at") >= lo)
        part = (part if hi is None else part.where(F.col("_at") < hi)).drop("_at")
        (part if change is None else change(part)).coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(f"{folder}/in")
    return folder


def _appended(s, folder, make):
    """The rows that a stream of the event files has given in the end, and its run."""
    stream = make(streams.replay(s, f"{folder}/in"))
    run = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/log").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return s.read.schema(stream.schema).parquet(f"{folder}/out"), run


def _sessions(s, d):
    """All sessions: those that the watermark closes, and the last ones, closed by an event long after all others, which is left out again."""
    folder = _event_files(s, d)
    end = table(s, d, "events").agg(F.max("ts").alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), (F.col("ts") + F.expr("INTERVAL 30 DAYS")).alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    end.coalesce(1).write.mode("append").parquet(f"{folder}/in")
    return _appended(s, folder, streams.session_walks)[0].where("user_id >= 0")


@query("stream_transitions")
def _(s, d):
    return _appended(s, _event_files(s, d), streams.transitions)[0].groupBy("ctx", "sym").agg(F.sum("n").cast("long").alias("n"))


def _windowed(s, d, slide=None, width="1 day"):
    users = _appended(s, _event_files(s, d), lambda x: streams.window_users(x, width, slide))[0]
    return streams.counted(users).select(F.unix_timestamp("start").alias("start"), "allele_id", "k")


_add("stream_window_carriers", lambda s, d: _windowed(s, d))
_add("stream_sliding_carriers", lambda s, d: _windowed(s, d, "1 day", "7 days"))


@query("stream_session_walks")
def _(s, d):
    return _sessions(s, d).select("user_id", F.unix_timestamp("start").alias("start"), F.size("labels").cast("long").alias("n"), F.array_join("labels", ",").alias("labels"))


@query("stream_session_codes")
def _(s, d):
    """Closed sessions with their end symbol, coded by the book of the users' whole walks; transitions that it lacks by the escape and the node's number."""
    paths, index = _paths(s, d, "events")
    index = cut(index)
    book = cut(codec.fit(cut(paths), escape="literal"))
    width = max(1, (index.count() - 1).bit_length())
    coded = codec.encode(streams.ended(_sessions(s, d), index), book, escape="literal", width=width)
    return coded.select("path_id.user_id", F.unix_timestamp("path_id.start").alias("start"), "n_symbols", "n_bits", "status")


@query("stream_deduplicated")
def _(s, d):
    """Events that come twice in a file count once."""
    folder = _event_files(s, d, lambda part: part.unionByName(part))
    return _appended(s, folder, streams.deduplicated)[0].groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_late_rows")
def _(s, d):
    """The events of the first day come again after all others, under new ids: they are dropped, and counted."""
    folder = _event_files(s, d)
    events = table(s, d, "events")
    first = events.agg(F.min("ts").alias("_first"))
    late = events.crossJoin(F.broadcast(first)).where(F.col("ts") < F.col("_first") + F.expr("INTERVAL 1 DAY")).drop("_first").withColumn("event_id", -1 - F.col("event_id"))
    late.coalesce(1).write.mode("append").parquet(f"{folder}/in")
    out, run = _appended(s, folder, streams.deduplicated)
    dropped = streams.late_rows(run)
    return out.agg(F.count(F.lit(1)).alias("kept")).select("kept", F.lit(dropped).cast("long").alias("dropped"))


def queries() -> dict[str, Query]:
    return dict(REGISTRY)
