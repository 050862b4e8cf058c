"""Paths of labels or of edge ids as arrays of contiguous node numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.session import cut


def node_index(labels: DataFrame, col: str = "label") -> DataFrame:
    """(label, idx): distinct labels numbered from 0 in label order.

    A range sort, then the number of labels in the partitions before each one: no
    task sees more than its own range, and the driver one count per partition.
    """
    placed = cut(labels.select(F.col(col).alias("label")).distinct().orderBy("label").withColumn("_id", F.monotonically_increasing_id()))
    part, row = F.call_function("shiftright", "_id", F.lit(33)), F.col("_id").bitwiseAND((1 << 33) - 1)
    sizes = placed.groupBy(part.alias("_part")).agg(F.count(F.lit(1)).alias("_n"))
    offset = F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("_part", offset.alias("_before"))  # a row per partition
    return placed.withColumn("_part", part).join(F.broadcast(offsets), "_part").select("label", (F.col("_before") + row).cast("long").alias("idx"))


def to_nodes(paths: DataFrame, index: DataFrame) -> DataFrame:
    """(path_id, nodes array<long>) of (path_id, labels)."""
    each = paths.select("path_id", F.posexplode_outer("labels").alias("at", "label"))
    found = each.join(index, "label", "left")
    own = F.filter(F.array_sort(F.collect_list(F.struct("at", "idx"))), lambda x: x["at"].isNotNull())
    return found.groupBy("path_id").agg(own.alias("s")).select("path_id", F.transform("s", lambda x: x["idx"]).alias("nodes"))


def adjacency(edges: DataFrame) -> DataFrame:
    """(src, dsts): sorted distinct successors."""
    return edges.groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("dsts"))


def expand_edges(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """(path_id, labels, ok) of (path_id, edge_ids): first source, then every destination; ok is false where edges do not chain or are unknown."""
    each = paths.select("path_id", F.posexplode("edge_ids").alias("at", "edge_id")).join(edges, "edge_id", "left")
    s = F.array_sort(F.collect_list(F.struct("at", "src", "dst")))
    own = each.groupBy("path_id").agg(s.alias("s"))
    chain = F.forall(F.zip_with(F.slice("s", 1, F.size("s") - 1), F.slice("s", 2, F.size("s") - 1), lambda x, y: F.coalesce(x["dst"] == y["src"], F.lit(False))), lambda ok: ok)
    known = F.forall("s", lambda x: x["src"].isNotNull())
    return own.select("path_id", F.concat(F.array(F.get("s", F.lit(0))["src"]), F.transform("s", lambda x: x["dst"])).alias("labels"), (chain & known).alias("ok"))
