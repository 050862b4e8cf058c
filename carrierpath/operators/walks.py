"""Haplotype-major walks over the backbone, their inverted index, and the equivalence with carrier rows.

A walk goes through the contigs in the order of their names; no step leads from one to another.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.session import cut
from . import ranges
from . import rows as R


def resolve_overlaps(alleles: DataFrame, inc: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(pairs that stay, pairs that lose): of overlapping alternatives on one contig of a haplotype the earlier start, then the least allele id, wins.

    Variants of one haplotype are scanned in order with the furthest end of the winners so far.
    """
    sv = alleles.where("class = 'SV'").select("contig", "allele_id", "pos", (F.col("pos") + F.col("ref_len")).alias("stop"))
    own = inc.join(sv, "allele_id").groupBy("hap_id", "contig").agg(F.array_sort(F.collect_list(F.struct("pos", "allele_id", "stop"))).alias("a"))
    start = F.struct(F.lit(-1).cast("long").alias("end"), F.array().cast("array<struct<allele_id:long,kept:boolean>>").alias("out"))

    def step(acc, x):
        ok = x["pos"] >= acc["end"]
        mark = F.struct(x["allele_id"].cast("long").alias("allele_id"), ok.alias("kept"))
        return F.struct(F.when(ok, x["stop"]).otherwise(acc["end"]).alias("end"), F.concat(acc["out"], F.array(mark)).alias("out"))

    judged = own.select("hap_id", F.explode(F.aggregate("a", start, step, lambda acc: acc["out"])).alias("x")).select("x.allele_id", "hap_id", "x.kept")
    return judged.where("kept").drop("kept"), judged.where("not kept").drop("kept")


def carried(alleles: DataFrame, inc: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Structural variants with their ends, and (path_id, variant) of those that a haplotype carries."""
    sv = alleles.where("class = 'SV'").select("contig", "allele_id", "pos", "ref_len")
    spans = sv.withColumn("stop", F.col("pos") + F.col("ref_len"))
    own = inc.select("allele_id", F.col("hap_id").alias("path_id")).distinct()
    return spans, own.join(F.broadcast(spans) if small(spans) else spans, "allele_id")


def replaced(segs: DataFrame, spans: DataFrame) -> DataFrame:
    """(contig, allele_id, _a, _z): the first and the last segment that an alternative replaces, found by its ends."""
    region = segs.groupBy("contig").agg(F.min("start").alias("_lo"), F.max("end").alias("_hi"))  # a row per contig
    inside = spans.join(F.broadcast(region), "contig").select("contig", "allele_id", F.greatest("pos", "_lo").alias("start"), F.least("stop", "_hi").alias("end")).where("start < end")
    ends = inside.join(segs.select("contig", "start", F.col("seg_no").alias("_a")), ["contig", "start"]).join(segs.select("contig", "end", F.col("seg_no").alias("_z")), ["contig", "end"])
    return ends.select("contig", "allele_id", "_a", "_z")


def _gone(segs: DataFrame, spans: DataFrame, carried: DataFrame) -> DataFrame:
    """(path_id, seg_no): segments that a haplotype's own alternatives replace."""
    covered = replaced(segs, spans).select(F.explode(F.sequence("_a", "_z")).alias("seg_no"), "allele_id")
    return carried.select("path_id", "allele_id").join(covered, "allele_id").select("path_id", "seg_no").distinct()


def links(segs: DataFrame, points: DataFrame, width: int = 100_000) -> DataFrame:
    """(contig, allele_id, link) of points (contig, allele_id, pos): the first segment that begins at or after the point, or one more than the contig's last."""
    within = ranges.covering(points, segs.select("contig", "seg_no", "start", "end"), width).select("contig", "allele_id", (F.col("seg_no") + F.when(F.col("start") < F.col("pos"), 1).otherwise(0)).alias("link"))
    bounds = segs.groupBy("contig").agg(F.min("start").alias("_lo"), F.max("end").alias("_hi"), F.min("seg_no").alias("_head"), (F.max("seg_no") + 1).alias("_tail"))  # a row per contig
    outside = points.join(F.broadcast(bounds), "contig").where("pos < _lo or pos >= _hi").select("contig", "allele_id", F.when(F.col("pos") < F.col("_lo"), F.col("_head")).otherwise(F.col("_tail")).alias("link"))
    return within.unionByName(outside)


def build(segs: DataFrame, alleles: DataFrame, inc: DataFrame, haps: DataFrame) -> DataFrame:
    """(path_id, contig, at, node, allele_id): every haplotype's nodes; ``at`` orders those of a contig.

    A carried structural variant replaces the reference segments that it covers, which are found by their ends, as both ends of
    a variant are cuts. Each haplotype gets all segments, then those covered by its own alternatives
    leave (an anti-join on segment and haplotype): work in proportion to the walks themselves.
    """
    spans, own = carried(alleles, inc)
    gone = _gone(segs, spans, own)
    every = haps.select(F.col("hap_id").alias("path_id")).crossJoin(F.broadcast(segs) if small(segs) else segs)
    ref = every.join(gone, ["path_id", "seg_no"], "left_anti").select("path_id", "contig", (2 * F.col("start") + 1).alias("at"), F.concat(F.lit("R"), F.col("seg_no").cast("string")).alias("node"), F.lit(None).cast("long").alias("allele_id"))
    alt = own.select("path_id", "contig", (2 * F.col("pos")).alias("at"), F.concat(F.lit("A"), F.col("allele_id").cast("string")).alias("node"), "allele_id")
    return ref.unionByName(alt)


def step_counts(segs: DataFrame, alleles: DataFrame, inc: DataFrame, h: int, names: DataFrame | None = None, width: int = 100_000) -> DataFrame:
    """(src, dst, n): how often the walks of h haplotypes step from node to node, over all contigs in order; src is null at the start, dst at the end.

    Equal to counting the steps of :func:`build`, without building it. Link l leads from segment l - 1 to segment l. A haplotype leaves the
    reference only at links beside a segment that it lacks or where it has an alternative; all others pass
    the link. So the work follows the incidence, not haplotypes times segments. ``names`` (allele_id, name)
    gives alternatives other names than A and their id.
    """
    spans, own = carried(alleles, inc)
    gone = _gone(segs, spans, own)
    points = spans.select("contig", "allele_id", "pos")
    name = F.concat(F.lit("A"), F.col("allele_id").cast("string"))
    placed = links(segs, points, width).join(points, ["contig", "allele_id"])
    placed = placed.withColumn("name", name) if names is None else placed.join(names, "allele_id", "left").withColumn("name", F.coalesce("name", name))
    placed = placed.select("allele_id", "link", F.struct("contig", "pos", "name").alias("alt"))
    alts = own.select("path_id", "allele_id").join(F.broadcast(placed) if small(placed) else placed, "allele_id").select("path_id", F.col("link").cast("long").alias("link"), F.lit(0).alias("on"), "alt")
    # A lacking segment r is at links r and r + 1, and joins them to one stretch.
    sides = gone.select("path_id", F.explode(F.array(F.struct(F.col("seg_no").cast("long").alias("link"), F.lit(0).alias("on")), F.struct((F.col("seg_no") + 1).cast("long").alias("link"), F.lit(1).alias("on")))).alias("x"))
    left = alts.unionByName(sides.select("path_id", "x.link", "x.on"), allowMissingColumns=True)
    left = left.groupBy("path_id", "link").agg(F.max("on").alias("on"), F.array_sort(F.collect_list("alt")).alias("alts"))
    left = cut(left)
    stretch = F.sum(1 - F.col("on")).over(Window.partitionBy("path_id").orderBy("link").rowsBetween(Window.unboundedPreceding, 0))
    own = left.withColumn("stretch", stretch).groupBy("path_id", "stretch").agg(
        F.min("link").alias("_a"), F.max("link").alias("_z"), F.array_sort(F.collect_list(F.when(F.size("alts") > 0, F.struct("link", "alts")))).alias("s")
    )
    last = segs.agg(F.coalesce(F.max("seg_no") + 1, F.lit(0)).cast("long").alias("_last"))  # one row
    ref = lambda link: F.concat(F.lit("R"), link.cast("string"))
    nodes = F.transform(F.flatten(F.transform("s", lambda x: x["alts"])), lambda x: x["name"])
    first, after = F.when(F.col("_a") > 0, ref(F.col("_a") - 1)), F.when(F.col("_z") < F.col("_last"), ref(F.col("_z")))
    steps = F.arrays_zip(F.concat(F.array(first), nodes).alias("src"), F.concat(nodes, F.array(after)).alias("dst"))
    bent = own.crossJoin(F.broadcast(last)).select(F.explode(steps).alias("t")).select(F.col("t").getField("src").alias("src"), F.col("t").getField("dst").alias("dst"))
    passed = segs.select(F.col("seg_no").cast("long").alias("link")).unionByName(last.select(F.col("_last").alias("link"))).crossJoin(F.broadcast(last))
    kept = passed.join(left.groupBy("link").agg(F.count(F.lit(1)).alias("_n")), "link", "left").select(
        F.when(F.col("link") > 0, ref(F.col("link") - 1)).alias("src"), F.when(F.col("link") < F.col("_last"), ref(F.col("link"))).alias("dst"), (F.lit(h) - F.coalesce("_n", F.lit(0))).cast("long").alias("n")
    )
    both = kept.where("n > 0").unionByName(bent.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")))
    return both.where("src is not null or dst is not null").groupBy("src", "dst").agg(F.sum("n").cast("long").alias("n"))


#: Rows of a variant catalogue (under 100 bytes each) up to which it is broadcast.
SMALL = 200_000


def small(df: DataFrame) -> bool:
    return df.limit(SMALL + 1).count() <= SMALL


def numbered(walk: DataFrame) -> DataFrame:
    """Adds seq from 0 in the order of contig and ``at``."""
    return walk.withColumn("seq", (F.row_number().over(Window.partitionBy("path_id").orderBy("contig", "at", "node")) - 1).cast("int"))


def site_lists(inc: DataFrame, alleles: DataFrame) -> DataFrame:
    """(path_id, alleles): the ordered alleles that a haplotype carries, without backbone."""
    own = inc.select("allele_id", "hap_id").distinct().join(alleles.select("allele_id", "contig", "pos"), "allele_id")
    return own.groupBy(F.col("hap_id").alias("path_id")).agg(F.array_sort(F.collect_list(F.struct("contig", "pos", "allele_id"))).alias("a")).select("path_id", F.col("a.allele_id").alias("alleles"))


def edges_of(walk: DataFrame) -> DataFrame:
    """(src, dst, path_id) of every step within a contig."""
    w = Window.partitionBy("path_id", "contig").orderBy("at", "node")
    return walk.select("path_id", F.col("node").alias("src"), F.lead("node").over(w).alias("dst")).where("dst is not null")


def edge_index(walk: DataFrame, h: int, policy: str = "min_cost") -> DataFrame:
    """Carrier rows keyed by edge 'src>dst': the inverted index, itself adaptively encoded."""
    pairs = edges_of(walk).select(F.concat_ws(">", "src", "dst").alias("allele_id"), F.col("path_id").alias("hap_id"), F.lit("edge").alias("class"))
    return R.encode(pairs, h, policy)


def to_incidence(walk: DataFrame) -> DataFrame:
    return walk.where("allele_id is not null").select("allele_id", F.col("path_id").alias("hap_id")).distinct()


def verify_dual(inc: DataFrame, walk: DataFrame) -> DataFrame:
    """(allele_id, hap_id, side) where carriers and traversers of the alternative's edges differ; must be empty."""
    own = inc.select("allele_id", "hap_id").distinct().withColumn("_r", F.lit(1))
    into = edges_of(walk).where(F.col("dst").startswith("A")).select(F.substring("dst", 2, 20).cast("long").alias("allele_id"), F.col("path_id").alias("hap_id"))
    out = edges_of(walk).where(F.col("src").startswith("A")).select(F.substring("src", 2, 20).cast("long").alias("allele_id"), F.col("path_id").alias("hap_id"))
    seen = into.unionByName(out).distinct().withColumn("_w", F.lit(1))
    return own.join(seen, ["allele_id", "hap_id"], "full").where("_r is null or _w is null").select("allele_id", "hap_id", F.when(F.col("_r").isNull(), "walk only").otherwise("row only").alias("side"))


def path_of(walk: DataFrame, paths: list) -> DataFrame:
    return numbered(walk.where(F.col("path_id").isin(list(paths)))).select("path_id", "seq", "node")


def neighborhood(walk: DataFrame, allele, radius: int, unit: str = "steps") -> DataFrame:
    """(path_id, offset, node) around an allele on each of its carriers, within steps or bases."""
    steps = walk.where(F.col("allele_id") == allele).select("path_id", "contig", F.col("at").alias("_at"))
    if unit == "bp":
        near = walk.join(steps, ["path_id", "contig"]).where(F.abs(F.col("at") - F.col("_at")) <= 2 * radius)
        return near.select("path_id", F.floor((F.col("at") - F.col("_at")) / 2).alias("offset"), "node")
    own = numbered(walk.join(steps.select("path_id", "contig"), ["path_id", "contig"], "left_semi"))
    centre = own.where(F.col("allele_id") == allele).select("path_id", F.col("seq").alias("_s"))
    return own.join(centre, "path_id").where(F.abs(F.col("seq") - F.col("_s")) <= radius).select("path_id", (F.col("seq") - F.col("_s")).alias("offset"), "node")


def successors(walk: DataFrame) -> DataFrame:
    """(src, dst, n): how many walks step from src to dst."""
    return edges_of(walk).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def before(walk: DataFrame, a: str, c: str) -> DataFrame:
    """(path_id, a_first) of walks with both nodes: whether the first a comes before the first c."""
    at = lambda x: F.min(F.when(F.col("node") == x, F.struct("contig", "at")))
    return walk.where(F.col("node").isin(a, c)).groupBy("path_id").agg(at(a).alias("_a"), at(c).alias("_c")).where("_a is not null and _c is not null").select("path_id", (F.col("_a") < F.col("_c")).alias("a_first"))


def local_haplotypes(walk: DataFrame, lo: int, hi: int, contig: str | None = None) -> DataFrame:
    """(nodes, n): groups of walks with the same nodes that begin in lo <= position < hi, of one contig; without it, of the only one."""
    local = walk.where((F.col("at") >= 2 * lo) & (F.col("at") < 2 * hi))
    if contig is not None:
        local = local.where(F.col("contig") == contig)
    own = local.groupBy("path_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "node"))), lambda x: x["node"]), ",").alias("nodes"))
    return own.groupBy("nodes").agg(F.count(F.lit(1)).alias("n"))
