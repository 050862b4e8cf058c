"""Walks as runs: each alternative with the reference segments that follow it until the next one.

Equal to the rows of :func:`walks.build`, which hold every node of every haplotype. A table of runs (path_id, contig, at, node,
allele_id, first, last) has one row for the begin of each contig (``at``, ``node`` and ``allele_id`` null) and one for each
carried alternative; the reference segments ``first`` to ``last`` come after it, none if first > last. So it grows with the
incidence, and nodes are listed only where a result has them, after the last shuffle.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import bitops as B
from . import rows as R
from . import walks


def build(segs: DataFrame, alleles: DataFrame, inc: DataFrame, haps: DataFrame, names: DataFrame | None = None) -> DataFrame:
    """The runs of every haplotype; ``names`` (allele_id, name) gives alternatives other names than A and their id.

    What a carried alternative replaces begins at its own link, so the reference goes on behind the furthest end of
    those before it: one window per path and contig over its alternatives.
    """
    spans, carried = walks.carried(alleles, inc)
    points = spans.select("contig", "allele_id", "pos")
    ends = walks.replaced(segs, spans).select("contig", "allele_id", F.col("_z").cast("long").alias("end"))
    placed = points.join(walks.links(segs, points), ["contig", "allele_id"], "left").join(ends, ["contig", "allele_id"], "left").drop("pos")
    name = F.concat(F.lit("A"), F.col("allele_id").cast("string"))
    placed = placed.withColumn("node", name) if names is None else placed.join(names, "allele_id", "left").withColumn("node", F.coalesce("name", name)).drop("name")
    own = carried.select("path_id", "contig", "allele_id", "pos").join(F.broadcast(placed) if walks.small(placed) else placed, ["contig", "allele_id"])
    alts = own.select(
        "path_id", "contig", (2 * F.col("pos")).alias("at"), "node", "allele_id",
        F.coalesce("link", F.lit(0)).cast("long").alias("link"), "end",
    )
    bounds = segs.groupBy("contig").agg(F.min("seg_no").cast("long").alias("link"), (F.max("seg_no") + 1).cast("long").alias("_tail"))  # a row per contig
    begins = haps.select(F.col("hap_id").alias("path_id")).crossJoin(F.broadcast(bounds.select("contig", "link")))
    tails = bounds.select("contig", "_tail")
    both = begins.unionByName(alts, allowMissingColumns=True).join(F.broadcast(tails), "contig", "left").repartition(_tasks(segs), "path_id")
    w = _order("path_id", "contig")
    so_far = w.rowsBetween(Window.unboundedPreceding, 0)
    first = F.greatest("link", F.coalesce(F.max("end").over(so_far) + 1, F.col("link")))
    until = F.coalesce(F.lead("link").over(w), "_tail", F.lit(0)) - 1
    known = F.max(F.col("at").isNull()).over(so_far)  # a haplotype that was not asked for has its alternatives alone
    out = both.select("path_id", "contig", "at", "node", "allele_id", first.alias("first"), until.alias("_until"), known.alias("_known"))
    return out.select("path_id", "contig", "at", "node", "allele_id", "first", F.when(F.col("_known"), F.greatest("_until", F.col("first") - 1)).otherwise(F.col("first") - 1).alias("last"))


def _tasks(df: DataFrame) -> int:
    """Runs are few, but their nodes are many: so many tasks that all cores list them."""
    spark = df.sparkSession
    return max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))


def _order(*by: str):
    """The begin of a contig has nulls, which come first."""
    return Window.partitionBy(*by).orderBy(*([] if "contig" in by else ["contig"]), "at", "node")


def _ref(seg: Column) -> Column:
    return F.concat(F.lit("R"), seg.cast("string"))


def _head() -> Column:
    """Number of the run's first node: that of its first segment, less one for an alternative."""
    return F.col("first") - F.col("node").isNotNull().cast("long")


def _listed(runs: DataFrame, lo: Column, hi: Column, *keep: str) -> DataFrame:
    """(*keep, no, node): a row for each node from number lo to hi of a run; no shuffle."""
    each = runs.withColumn("_lo", lo).withColumn("_hi", hi).where("_lo <= _hi").select("*", F.explode(F.sequence("_lo", "_hi")).alias("no"))
    return each.select(*keep, "no", F.when(F.col("no") < F.col("first"), F.col("node")).otherwise(_ref(F.col("no"))).alias("node"))


def placed(runs: DataFrame, *by: str) -> DataFrame:
    """Adds seq, the place of a run's first node among those of its path (and contig, if ``by`` says so)."""
    size = F.col("last") - _head() + 1
    return runs.withColumn("seq", F.coalesce(F.sum(size).over(_order(*by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))


#: Tiles have 2 ** TILE segments; groups of paths for a task, within which equal stretches are listed together.
TILE, GROUPS = 9, 8


def numbered(runs: DataFrame) -> DataFrame:
    """(path_id, contig, seq, node): all nodes, as :func:`walks.numbered` has them.

    Runs are cut at tiles of the segments. Of a group of paths those that have the same part of a run at the same place are listed together, node by
    node, so that equal values follow one another: written path by path, a node would be as far from its next mention as a walk is long, and no file could store it once.
    """
    tasks = _tasks(runs)
    own = runs.withColumn("_group", F.pmod(F.xxhash64("path_id"), F.lit(GROUPS * tasks))).repartition(tasks, "_group")
    own = placed(own, "_group", "path_id").withColumn("_head", _head()).where("_head <= last")
    each = own.withColumn("_tile", F.explode(F.sequence(F.shiftright("_head", TILE), F.shiftright("last", TILE))))  # an alternative before all segments has number -1
    lo, hi = F.greatest("_head", F.col("_tile") * (1 << TILE)), F.least("last", (F.col("_tile") + 1) * (1 << TILE) - 1)
    alt = F.when(lo < F.col("first"), F.col("node"))
    each = each.select("_group", "contig", lo.alias("_lo"), hi.alias("_hi"), (F.col("seq") - F.col("_head")).alias("_seq"), alt.alias("_alt"), "path_id")
    same = each.groupBy("_group", "contig", "_lo", "_hi", "_seq", "_alt").agg(F.collect_list("path_id").alias("_paths"))
    nodes = same.select("*", F.explode(F.sequence("_lo", "_hi")).alias("no"))
    node = F.when(F.col("_alt").isNotNull() & (F.col("no") == F.col("_lo")), F.col("_alt")).otherwise(_ref(F.col("no")))
    return nodes.select("_paths", "contig", (F.col("_seq") + F.col("no")).alias("seq"), node.alias("node")).select(F.explode("_paths").alias("path_id"), "contig", "seq", "node")


def by_path(runs: DataFrame, index: DataFrame) -> DataFrame:
    """(path_id, heads, firsts, lasts): a row for each path, its runs in order; heads are the alternatives' numbers in ``index`` (label, idx), null at a begin."""
    own = runs.join(index.select(F.col("label").alias("node"), "idx"), "node", "left")
    part = F.struct("contig", F.coalesce("at", F.lit(-(1 << 62))).alias("at"), "node", "idx", "first", "last")
    held = own.groupBy("path_id").agg(F.array_sort(F.collect_list(part)).alias("s")).repartition(_tasks(runs), "path_id")
    return held.select("path_id", F.col("s.idx").alias("heads"), F.col("s.first").alias("firsts"), F.col("s.last").alias("lasts"))


def spine(segs: DataFrame, index: DataFrame) -> np.ndarray:
    """Numbers in ``index`` of the segments, by segment; one that no walk has is -9."""
    own = segs.select("seg_no", _ref(F.col("seg_no")).alias("label")).join(index, "label").select(F.col("seg_no").cast("long").alias("seg_no"), "idx").toArrow()
    at = own.column(0).to_numpy()
    out = np.full(int(at.max(initial=-1)) + 1, -9, dtype=np.int64)
    out[at] = own.column(1).to_numpy()
    return out


def bends(runs: DataFrame) -> DataFrame:
    """(path_id, src, dst): the steps within a contig that touch an alternative; all others lead from a segment of a run to the next one."""
    w = _order("path_id", "contig")
    held = F.col("first") <= F.col("last")
    leave = F.when(F.col("node").isNotNull() & held, F.struct(F.col("node").alias("src"), _ref(F.col("first")).alias("dst")))
    end = F.when(held, _ref(F.col("last"))).otherwise(F.col("node"))
    enter = F.when(F.col("_next").isNotNull() & end.isNotNull(), F.struct(end.alias("src"), F.col("_next").alias("dst")))
    each = runs.withColumn("_next", F.lead("node").over(w)).select("path_id", F.explode(F.array(leave, enter)).alias("t")).where("t is not null")
    return each.select("path_id", "t.src", "t.dst")


def _straight(segs: DataFrame) -> DataFrame:
    """(contig, link): segments that another one of their contig follows."""
    last = segs.groupBy("contig").agg(F.max("seg_no").alias("_last"))  # a row per contig
    return segs.join(F.broadcast(last), "contig").where("seg_no < _last").select("contig", F.col("seg_no").cast("long").alias("link"))


def verify_dual(inc: DataFrame, runs: DataFrame) -> DataFrame:
    """(allele_id, hap_id, side) where carriers and traversers of the alternative's edges differ; must be empty."""
    own = inc.select("allele_id", "hap_id").distinct().withColumn("_r", F.lit(1))
    ends = bends(runs).select(F.col("path_id").alias("hap_id"), F.explode(F.array("src", "dst")).alias("node")).where(F.col("node").startswith("A"))
    seen = ends.select(F.substring("node", 2, 20).cast("long").alias("allele_id"), "hap_id").distinct().withColumn("_w", F.lit(1))
    return own.join(seen, ["allele_id", "hap_id"], "full").where("_r is null or _w is null").select("allele_id", "hap_id", F.when(F.col("_r").isNull(), "walk only").otherwise("row only").alias("side"))


def successors(runs: DataFrame, segs: DataFrame) -> DataFrame:
    """(src, dst, n): how many walks step from src to dst; those within runs from the runs that begin and end at each segment."""
    bent = bends(runs).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    marks = F.array(F.struct(F.col("first").alias("link"), F.lit(1).alias("d")), F.struct(F.col("last").alias("link"), F.lit(-1).alias("d")))
    turns = runs.where("first < last").select(F.explode(marks).alias("x")).groupBy("x.link").agg(F.sum("x.d").alias("d"))
    passed = F.sum(F.coalesce("d", F.lit(0))).over(Window.partitionBy("contig").orderBy("link").rowsBetween(Window.unboundedPreceding, 0))
    straight = segs.select("contig", F.col("seg_no").cast("long").alias("link")).join(turns, "link", "left").select("link", passed.cast("long").alias("n")).where("n > 0")
    return bent.unionByName(straight.select(_ref(F.col("link")).alias("src"), _ref(F.col("link") + 1).alias("dst"), "n"))


def edge_index(runs: DataFrame, segs: DataFrame, h: int, policy: str = "min_cost") -> DataFrame:
    """Carrier rows keyed by edge 'src>dst' of the runs of all h haplotypes, as :func:`walks.edge_index` has them.

    The row of a link between two segments is made from the haplotypes that do not pass it, which are few.
    """
    pairs = bends(runs).select(F.concat_ws(">", "src", "dst").alias("allele_id"), F.col("path_id").alias("hap_id"), F.lit("edge").alias("class"))
    bounds = segs.groupBy("contig").agg((F.max("seg_no") - 1).cast("long").alias("_end"))  # a row per contig
    until = F.coalesce(F.lead("first").over(_order("path_id", "contig")) - 1, "_end")
    gaps = runs.join(F.broadcast(bounds), "contig").select("path_id", "contig", "last", until.alias("_until")).where("last <= _until")
    absent = gaps.select(F.col("path_id").alias("hap_id"), "contig", F.explode(F.sequence("last", "_until")).alias("link"))
    edge = F.concat_ws(">", _ref(F.col("link")), _ref(F.col("link") + 1))
    straight = R.encode_complement(absent, _straight(segs), h, policy).select(edge.alias("allele_id"), F.lit("edge").alias("class"), "k", "enc", "carriers", "words", "bits")
    return R.encode(pairs, h, policy).unionByName(straight)


def neighborhood(runs: DataFrame, segs: DataFrame, allele, radius: int, unit: str = "steps") -> DataFrame:
    """(path_id, offset, node) around an allele on each of its carriers, within steps or bases; only the nodes that are near are listed."""
    carriers = runs.where(F.col("allele_id") == allele)
    own = runs.join(carriers.select("path_id", "contig"), ["path_id", "contig"], "left_semi")
    if unit == "bp":
        centre = carriers.select("path_id", "contig", F.col("at").alias("_at"))
        places = carriers.select("contig", F.col("at").alias("_at")).distinct()  # a row per contig
        starts = segs.select("contig", F.col("seg_no").cast("long").alias("no"), (2 * F.col("start") + 1).alias("_place"))
        close = starts.join(F.broadcast(places), "contig").where(F.abs(F.col("_place") - F.col("_at")) <= 2 * radius)
        span = close.groupBy("contig").agg(F.min("no").alias("_from"), F.max("no").alias("_to"))
        near = own.join(centre, ["path_id", "contig"]).join(F.broadcast(span), "contig", "left")
        alts = near.where(F.abs(F.col("at") - F.col("_at")) <= 2 * radius).select("path_id", "_at", F.col("at").alias("_place"), "node")
        refs = _listed(near, F.greatest("first", "_from"), F.least("last", "_to"), "path_id", "contig", "_at").where(F.col("node").isNotNull())
        refs = refs.join(close.select("contig", "no", "_place"), ["contig", "no"]).select("path_id", "_at", "_place", "node")
        return alts.unionByName(refs).select("path_id", F.floor((F.col("_place") - F.col("_at")) / 2).alias("offset"), "node")
    own = placed(own, "path_id", "contig").withColumn("_head", _head())
    centre = own.where(F.col("allele_id") == allele).select("path_id", "contig", F.col("seq").alias("_s"))
    own = own.join(centre, ["path_id", "contig"]).withColumn("_off", F.col("seq") - F.col("_s") - F.col("_head"))  # offset of a node, less its number
    near = _listed(own, F.greatest(F.col("_head"), -radius - F.col("_off")), F.least(F.col("last"), radius - F.col("_off")), "path_id", "_off")
    return near.select("path_id", (F.col("no") + F.col("_off")).alias("offset"), "node")


def local_haplotypes(runs: DataFrame, segs: DataFrame, lo: int, hi: int, contig: str | None = None) -> DataFrame:
    """(nodes, n): groups of walks with the same nodes that begin in lo <= position < hi, of one contig; without it, of the only one.

    Walks are grouped by their runs; the nodes are listed once for each group.
    """
    own = runs if contig is None else runs.where(F.col("contig") == contig)
    span = segs.where((F.col("start") >= lo) & (F.col("start") < hi)).groupBy("contig").agg(F.min("seg_no").cast("long").alias("_from"), F.max("seg_no").cast("long").alias("_to"))
    cut = own.join(F.broadcast(span), "contig", "left").withColumn("first", F.greatest("first", "_from")).withColumn("last", F.least("last", "_to"))
    held = F.coalesce((F.col("first") <= F.col("last")) & F.col("_from").isNotNull(), F.lit(False))
    cut = cut.withColumn("node", F.when((F.col("at") >= 2 * lo) & (F.col("at") < 2 * hi), F.col("node"))).withColumn("_held", held).where("_held or node is not null")
    part = F.struct("contig", "at", "node", F.when(F.col("_held"), F.col("first")).alias("first"), F.when(F.col("_held"), F.col("last")).alias("last"))
    key = F.transform(F.array_sort(F.collect_list(part)), lambda x: F.struct(x["node"].alias("node"), x["first"].alias("first"), x["last"].alias("last")))
    groups = cut.groupBy("path_id").agg(key.alias("key")).groupBy("key").agg(F.count(F.lit(1)).alias("n")).repartition(_tasks(segs), "key")
    none = F.array().cast("array<string>")
    nodes = lambda x: F.concat(F.when(x["node"].isNotNull(), F.array(x["node"])).otherwise(none), F.when(x["first"].isNotNull(), F.transform(F.sequence(x["first"], x["last"]), _ref)).otherwise(none))
    return groups.select(F.array_join(F.flatten(F.transform("key", nodes)), ",").alias("nodes"), "n")
