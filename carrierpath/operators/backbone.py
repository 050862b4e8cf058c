"""Graph views of one region: backbone segments, bubbles, annotations, side nodes.

Segments are numbered by the distinct cuts of a contig in order, and on from contig to contig in the order of
their names, so that a number names one segment of the whole graph. The variant catalogue is small beside
the incidence: one window per contig orders it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import ranges


def cuts(alleles: DataFrame, lo: int, hi: int, mode: str = "sv", tile: int = 1000) -> DataFrame:
    """Distinct interior cuts (contig, cut): both ends of structural variants ('sv'), tile bounds too ('tiled'), or both ends of every variant ('every_variant')."""
    own = alleles if mode == "every_variant" else alleles.where("class = 'SV'")
    ends = own.select("contig", F.explode(F.array("pos", F.col("pos") + F.col("ref_len"))).alias("cut"))
    if mode == "tiled":
        first = (lo // tile + 1) * tile
        tiles = alleles.select("contig").distinct().select("contig", F.explode(F.sequence(F.lit(first).cast("long"), F.lit(max(first, hi - 1)).cast("long"), F.lit(tile).cast("long"))).alias("cut"))
        ends = ends.unionByName(tiles)
    return ends.where((F.col("cut") > lo) & (F.col("cut") < hi)).distinct()


def _in_all(own: DataFrame, col: str) -> DataFrame:
    """``own`` with its numbers ``col``, from 0 in each contig, counted on from contig to contig."""
    sizes = own.groupBy("contig").agg((F.max(col) + 1).alias("_n"))  # a row per contig
    offset = F.coalesce(F.sum("_n").over(Window.orderBy("contig").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select(F.col("contig").alias("_contig"), offset.alias("_before"))
    return own.join(offsets, F.col("contig").eqNullSafe(F.col("_contig"))).withColumn(col, (F.col(col) + F.col("_before")).cast("long")).drop("_contig", "_before")


def segments(alleles: DataFrame, lo: int, hi: int, mode: str = "sv", tile: int = 1000) -> DataFrame:
    """(contig, seg_no, start, end), half-open, in order from 0; the next contig goes on."""
    bounds = cuts(alleles, lo, hi, mode, tile).unionByName(alleles.select("contig").distinct().withColumn("cut", F.lit(lo).cast("long")))
    w = Window.partitionBy("contig").orderBy("cut")
    own = bounds.select("contig", (F.row_number().over(w) - 1).alias("seg_no"), F.col("cut").alias("start"), F.coalesce(F.lead("cut").over(w), F.lit(hi).cast("long")).alias("end"))
    return _in_all(own, "seg_no").select("contig", "seg_no", "start", "end")


def compact(segs: DataFrame, keep: DataFrame) -> DataFrame:
    """Segments joined across cuts that are not in ``keep`` (contig, cut)."""
    kept = segs.join(keep.select("contig", F.col("cut").alias("start"), F.lit(1).alias("_keep")), ["contig", "start"], "left")
    w = Window.partitionBy("contig").orderBy("start")
    island = F.sum(F.coalesce("_keep", F.lit(0))).over(w.rowsBetween(Window.unboundedPreceding, 0))
    own = kept.withColumn("seg_no", island.cast("int")).groupBy("contig", "seg_no").agg(F.min("start").alias("start"), F.max("end").alias("end"))
    return _in_all(own, "seg_no").select("contig", "seg_no", "start", "end")


def bubbles(segs: DataFrame, alleles: DataFrame) -> DataFrame:
    """(contig, allele_id, before_seg, first_seg, after_seg): the alternative of each structural variant links the segment that ends at its begin
    with the one that begins at its end; first_seg is null for an insertion."""
    sv = alleles.where("class = 'SV'").withColumn("stop", F.col("pos") + F.col("ref_len"))
    ends = segs.select("contig", F.col("end").alias("pos"), F.col("seg_no").alias("before_seg"))
    starts = segs.select("contig", F.col("start").alias("stop"), F.col("seg_no").alias("after_seg"))
    heads = segs.groupBy("contig").agg(F.min("seg_no").alias("_head"))
    out = sv.join(ends, ["contig", "pos"], "left").join(starts, ["contig", "stop"], "left").join(heads, "contig", "left")
    return out.select("contig", "allele_id", "before_seg", F.when(F.col("ref_len") > 0, F.coalesce(F.col("before_seg") + 1, F.col("_head"))).alias("first_seg"), "after_seg")


def annotate(segs: DataFrame, snv: DataFrame, width: int = 100_000) -> DataFrame:
    """(contig, allele_id, pos, seg_no): each short variant on the segment that covers it."""
    return ranges.covering(snv.select("contig", "allele_id", "pos"), segs, width).select("contig", "allele_id", "pos", "seg_no")


def select(alleles: DataFrame, snv_modulo: int | None = None, snv_rest: int = 0, snv_fraction: float | None = None, seed: int = 0) -> DataFrame:
    """Structural variants and a reproducible part of the short ones: by id modulo, by a hashed fraction, or none."""
    keep = F.lit(False)
    if snv_modulo:
        keep = F.col("allele_id") % snv_modulo == snv_rest
    elif snv_fraction is not None:
        keep = F.pmod(F.xxhash64("allele_id", F.lit(seed)), F.lit(1_000_000)) < int(snv_fraction * 1_000_000)
    return alleles.where((F.col("class") == "SV") | keep)


def graph(segs: DataFrame, alleles: DataFrame, side_nodes: bool = False) -> tuple[DataFrame, DataFrame]:
    """Nodes (node, kind, contig, start, end, allele_id) and edges (src, dst, kind) by name: R<seg>, A<allele>, S<allele>."""
    r = lambda c: F.concat(F.lit("R"), F.col(c).cast("string"))
    none = F.lit(None).cast("long")
    b = bubbles(segs, alleles)
    alt = F.concat(F.lit("A"), F.col("allele_id").cast("string"))
    nodes = segs.select(r("seg_no").alias("node"), F.lit("ref").alias("kind"), "contig", "start", "end", none.alias("allele_id")).unionByName(
        alleles.where("class = 'SV'").select(alt.alias("node"), F.lit("alt").alias("kind"), "contig", F.col("pos").alias("start"), (F.col("pos") + F.col("ref_len")).alias("end"), "allele_id")
    )
    w = Window.partitionBy("contig").orderBy("seg_no")
    links = segs.select(r("seg_no").alias("src"), F.lead(r("seg_no")).over(w).alias("dst"), F.lit("ref").alias("kind")).where("dst is not null")
    into = b.where("before_seg is not null").select(r("before_seg").alias("src"), alt.alias("dst"), F.lit("alt").alias("kind"))
    out = b.where("after_seg is not null").select(alt.alias("src"), r("after_seg").alias("dst"), F.lit("alt").alias("kind"))
    edges = links.unionByName(into).unionByName(out)
    if side_nodes:
        side = annotate(segs, alleles.where("class <> 'SV'"))
        name = F.concat(F.lit("S"), F.col("allele_id").cast("string"))
        nodes = nodes.unionByName(side.select(name.alias("node"), F.lit("side").alias("kind"), "contig", F.col("pos").alias("start"), (F.col("pos") + 1).alias("end"), "allele_id"))
        edges = edges.unionByName(side.select(r("seg_no").alias("src"), name.alias("dst"), F.lit("side").alias("kind")))
    return nodes, edges


def size(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(item, n): counts of nodes and edges by kind."""
    n = nodes.groupBy(F.concat(F.col("kind"), F.lit("_nodes")).alias("item")).agg(F.count(F.lit(1)).alias("n"))
    return n.unionByName(edges.groupBy(F.concat(F.col("kind"), F.lit("_edges")).alias("item")).agg(F.count(F.lit(1)).alias("n")))


def exchange_lines(nodes: DataFrame, edges: DataFrame, walks: DataFrame | None = None) -> DataFrame:
    """(value): segment, link and walk lines of the usual text form for graphs, sequences left out."""
    length = F.concat(F.lit("LN:i:"), (F.col("end") - F.col("start")).cast("string"))
    lines = nodes.select(F.concat_ws("\t", F.lit("S"), "node", F.lit("*"), length).alias("value"))
    lines = lines.unionByName(edges.select(F.concat_ws("\t", F.lit("L"), "src", F.lit("+"), "dst", F.lit("+"), F.lit("*")).alias("value")))
    if walks is not None:
        lines = lines.unionByName(walks.select(F.concat_ws("\t", F.lit("P"), F.col("path_id").cast("string"), F.concat_ws(",", F.transform("labels", lambda x: F.concat(x, F.lit("+")))), F.lit("*")).alias("value")))
    return lines
