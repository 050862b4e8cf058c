"""Classes of near duplicates from inverted lists: T-occurrence search, verified links, components.

An inverted list is a set of rows (key, doc). Documents that can be linked share a key; which of
them are is decided on their whole shingle sets. No list is expanded into pairs:

* every document is tried against the least and then the greatest member of each of its lists, and
  what links is contracted. That is linear in the lists, and settles lists of up to three;
* the lists that still hold several classes join their documents to families. A family is dealt into
  blocks of bounded size, and a task takes two blocks (or one with itself), builds the
  inverted lists of one, and searches them with the sets of the other. It returns only
  links that join two classes it has not joined yet, fewer than it has documents.

Every pair that shares a key thus ends up either tried or in one class. Rows grow with the
documents of a family times its blocks.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.memory import trimmed
from .common import cut, partitions, sized

#: Candidates of one query that are searched at once, and that go to one task.
BLOCK, PER_TASK = 512, 4096
#: Documents and shingles that a block of a family holds, about.
CELL_DOCS, CELL_HASHES = 512, 1 << 20
#: Most pairs (under 50 bytes each) that are broadcast to meet their sets, so that the sets are not shuffled.
BROADCAST_PAIRS = 500_000
#: Rows of links that a task takes, about.
TASK_ROWS = 50_000


# T-occurrence search ------------------------------------------------------------------


def divide_skip(lists: list[np.ndarray], least: int) -> tuple[np.ndarray, np.ndarray]:
    """Documents that stand in at least ``least`` of the sorted lists, and in how many.

    A document must be in at least ``least - n_long`` of the others if the n_long longest lists are set aside.
    Those others, the short ones, are merged; what reaches that count is looked up in
    the long ones by binary search.
    """
    lists = [x for x in lists if len(x)]
    if least <= 0 or len(lists) < least:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    lists = sorted(lists, key=len)
    # Each list set aside saves its merge and costs a search for every candidate.
    longest = len(lists[-1])
    n_long = min(least - 1, int(least / (0.01 * np.log2(longest + 1) + 1)), len(lists) - 1)
    short, long = lists[: len(lists) - n_long], lists[len(lists) - n_long :]
    if len(short) <= 8:
        docs, counts = _heap_merge(short)
    else:  # the same merge as one sort, where a heap in Python would be slow
        docs, counts = np.unique(np.concatenate(short), return_counts=True)
    for left, own in enumerate([*reversed(long), None]):
        enough = counts >= least - n_long + left  # what the lists not probed yet can still add
        docs, counts = docs[enough], counts[enough]
        if own is None or not len(docs):
            break
        place = np.searchsorted(own, docs)
        counts = counts + ((place < len(own)) & (own[np.minimum(place, len(own) - 1)] == docs))
    return docs, counts


def _heap_merge(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    docs: list[int] = []
    counts: list[int] = []
    for d in heapq.merge(*[x.tolist() for x in lists]):
        if docs and docs[-1] == d:
            counts[-1] += 1
        else:
            docs.append(d)
            counts.append(1)
    return np.array(docs, dtype=np.int64), np.array(counts, dtype=np.int64)


def search_block(query: np.ndarray, block: list[np.ndarray], percent: int) -> np.ndarray:
    """Places in ``block`` of the sets whose Jaccard similarity to the query is at least percent/100."""
    sizes = np.array([len(x) for x in block])
    owner = np.repeat(np.arange(len(block)), sizes)
    every = np.concatenate(block) if len(block) else np.zeros(0, dtype=np.int64)
    place = np.searchsorted(query, every)
    hit = (place < len(query)) & (query[np.minimum(place, len(query) - 1)] == every) if len(query) else np.zeros(len(every), dtype=bool)
    place, owner = place[hit], owner[hit]
    order = np.argsort(place, kind="stable")  # by token, documents ascending within it
    place, owner = place[order], owner[order]
    lists = np.split(owner, np.flatnonzero(np.diff(place)) + 1) if len(place) else []
    # The smallest overlap that any partner needs: percent of the larger of both sets.
    need = -(-percent * len(query) // 100)
    docs, counts = divide_skip(lists, max(1, need))
    union = len(query) + sizes[docs] - counts
    return docs[100 * counts >= percent * union]


def verified(pairs: DataFrame, sets: DataFrame, rows: int, percent: int = 80) -> DataFrame:
    """The pairs (x, y), a table of so many rows that was cut, whose sets (doc, hashes) are similar enough; x is the query, its ys the searched block."""
    counted = pairs.groupBy("x").agg(F.count(F.lit(1)).alias("n")).select("x", F.ceil(F.col("n") / PER_TASK).cast("int").alias("parts"))
    counted = cut(few(counted, rows))
    queries = sets.select(F.col("doc").alias("x"), "hashes").join(sized(counted, BROADCAST_PAIRS), "x").select(
        "x", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(-1).cast("long").alias("y"), F.lit(0).alias("kind"), "hashes"
    )
    placed = cut(few(pairs.join(sized(counted, BROADCAST_PAIRS), "x").select("x", F.pmod(F.xxhash64("y"), F.col("parts")).cast("int").alias("part"), "y"), rows))
    blocks = sets.select(F.col("doc").alias("y"), "hashes").join(sized(placed, BROADCAST_PAIRS), "y").select("x", "part", "y", F.lit(1).alias("kind"), "hashes")

    def run(batches):
        query, at, ids, block = None, None, [], []

        def flush():
            found = search_block(query, block, percent) if block else []
            out = pa.record_batch([pa.array([at[0]] * len(found), pa.int64()), pa.array([ids[i] for i in found], pa.int64())], names=["x", "y"])
            ids.clear()
            block.clear()
            return out

        for b in batches:
            x, part, y, kind, hashes = b.columns
            values, ends = hashes.flatten().to_numpy(), hashes.offsets.to_numpy() - hashes.offsets[0].as_py()
            for i, (x_, part_, y_, kind_) in enumerate(zip(x.to_pylist(), part.to_pylist(), y.to_pylist(), kind.to_pylist(), strict=True)):
                if (x_, part_) != at:
                    if block:
                        yield flush()
                    at, query = (x_, part_), None
                own = values[ends[i] : ends[i + 1]]
                if kind_ == 0:
                    query = own.copy()
                else:
                    ids.append(y_)
                    block.append(own.copy())
                    if len(block) >= BLOCK:
                        yield flush()
        if block:
            yield flush()

    both = queries.unionByName(blocks).repartition(partitions(pairs.sparkSession), "x", "part").sortWithinPartitions("x", "part", "kind", "y")
    return both.mapInArrow(trimmed(run), "x long, y long")


# Components ---------------------------------------------------------------------------


def few(df: DataFrame, rows: int) -> DataFrame:
    """``df`` in as many tasks as about so many rows need, at most all."""
    return df.coalesce(max(1, min(partitions(df.sparkSession), -(-rows // TASK_ROWS))))


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """(doc, root) of every document on a link (x, y): the least document it is connected with.

    Large and small stars in turn: neighbours are hung on the least of their neighbourhood
    until the links are stars; every step is a grouped minimum and a join.
    """
    e = cut(edges.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v")).where("u <> v").distinct())
    seen = _fingerprint(e)
    for _ in range(most):
        n = 2 * seen[0]
        if not n:
            break
        e = few(e, n)
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = few(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v"), n)
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = few(large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(low.select("u", F.col("m").alias("v"))), n)
        e = cut(few(small.distinct(), n))
        now = _fingerprint(e)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("doc"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("doc"), F.col("v").alias("root")).distinct())


def hung(edges: DataFrame, rows: int) -> DataFrame:
    """(doc, root): a smaller document that ``doc`` is connected with by links (x, y) of hubs x, not always the least; a few steps of :func:`components`."""
    star = edges.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
    named = edges.join(star, "x").select(F.col("y").alias("doc"), "m").unionByName(star.select(F.col("x").alias("doc"), "m"))
    own = cut(few(named.groupBy("doc").agg(F.min("m").alias("root")).where("root < doc"), rows))
    # The root may hang on another one.
    above = own.select(F.col("doc").alias("root"), F.col("root").alias("top"))
    return cut(few(own.join(sized(above, BROADCAST_PAIRS), "root", "left").select("doc", F.coalesce("top", "root").alias("root")), rows))


# Families -------------------------------------------------------------------------------


class Inverted:
    """Inverted lists of some sets of sorted hashes: places of sets, ascending, by hash."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(x) for x in sets], dtype=np.int64)
        every = np.concatenate(sets) if sets else np.zeros(0, dtype=np.int64)
        owner = np.repeat(np.arange(len(sets)), self.sizes)
        order = np.argsort(every, kind="stable")
        self.owner = owner[order]
        self.hashes, start = np.unique(every[order], return_index=True)
        self.ends = np.append(start, len(every))

    def partners(self, query: np.ndarray, percent: int) -> np.ndarray:
        """Places of the sets whose Jaccard similarity to the query is at least percent/100."""
        least = -(-percent * len(query) // 100)
        if not len(query) or not len(self.hashes):
            return np.zeros(0, dtype=np.int64)
        at = np.searchsorted(self.hashes, query)
        at = at[self.hashes[np.minimum(at, len(self.hashes) - 1)] == query]
        if len(at) < least:
            return np.zeros(0, dtype=np.int64)
        docs, counts = divide_skip([self.owner[self.ends[k] : self.ends[k + 1]] for k in at.tolist()], max(1, least))
        return docs[100 * counts >= percent * (len(query) + self.sizes[docs] - counts)]


def spanning_links(queries: list[tuple], others: list[tuple] | None, percent: int) -> list[tuple[int, int]]:
    """Links (x, y) between different classes that join all that can be joined between two blocks, or within one if ``others`` is None.

    A block has (doc, class, hashes). No more links than classes come out: what they joined before is not returned.
    """
    second = queries if others is None else others
    every = queries if others is None else [*queries, *others]
    _, label = np.unique(np.array([c for _, c, _ in every], dtype=np.int64), return_inverse=True)
    first = 0 if others is None else len(queries)
    index = Inverted([h for _, _, h in second])
    out = []
    for i, (doc, _, hashes) in enumerate(queries):
        theirs = label[first:]
        if (theirs == label[i]).all():
            continue
        for j in index.partners(hashes, percent).tolist():
            if theirs[j] != label[i]:
                out.append((doc, second[j][0]))
                label[label == theirs[j]] = label[i]
    return out


def family_links(left: DataFrame, sets: DataFrame, rows: int, percent: int, docs: int = CELL_DOCS, hashes: int = CELL_HASHES) -> DataFrame:
    """Links (x, y) between the classes of ``left`` (key, doc, class, first), so many rows of lists that were cut, with their least document, by blocks of families."""
    spark = left.sparkSession
    family = components(few(left, rows).select(F.col("doc").alias("x"), F.col("first").alias("y")))
    placed = few(left, rows).select("doc", "class").distinct().join(family, "doc").join(sets.select("doc", F.size("hashes").alias("n")), "doc")
    placed = cut(few(placed.select("doc", "class", F.col("root").alias("family"), "n"), rows))
    of = placed.groupBy("family").agg(F.greatest(F.ceil(F.count(F.lit(1)) / docs), F.ceil(F.sum("n") / hashes)).cast("int").alias("blocks"), (F.min("class") != F.max("class")).alias("mixed"))
    of = cut(few(of.where("mixed").select("family", "blocks"), rows))
    dealt = placed.join(sized(of, BROADCAST_PAIRS), "family").withColumn("block", F.pmod(F.xxhash64("doc"), F.col("blocks")).cast("int"))
    dealt = cut(dealt.select("doc", "class", "family", "block", "blocks"))
    cells = sets.join(sized(dealt, BROADCAST_PAIRS), "doc").withColumn("j", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cells = cells.select("family", F.least("block", "j").alias("i"), F.greatest("block", "j").alias("j"), "block", "doc", "class", "hashes")

    def run(batches):
        at, sides = None, ({}, {})

        def flush():
            (i, j), (first, second) = at[1:], sides
            one, two = list(first.values()), list(second.values())
            found = spanning_links(one, None if i == j else two, percent)
            first.clear()
            second.clear()
            return pa.record_batch([pa.array([x for x, _ in found], pa.int64()), pa.array([y for _, y in found], pa.int64())], names=["x", "y"])

        for b in batches:
            values, ends = b.column(6).flatten().to_numpy(), b.column(6).offsets.to_numpy() - b.column(6).offsets[0].as_py()
            for k, (fam, i, j, block, doc, cls) in enumerate(zip(*(c.to_pylist() for c in b.columns[:6]), strict=True)):
                if (fam, i, j) != at:
                    if at:
                        yield flush()
                    at = (fam, i, j)
                sides[int(block != i)][doc] = (doc, cls, values[ends[k] : ends[k + 1]].copy())
        if at:
            yield flush()

    return cells.repartition(partitions(spark), "family", "i", "j").sortWithinPartitions("family", "i", "j", "doc").mapInArrow(trimmed(run), "x long, y long")


def classes(lists: DataFrame, sets: DataFrame, percent: int = 80, docs: int = CELL_DOCS, hashes: int = CELL_HASHES) -> DataFrame:
    """(doc, class): the least document reachable by links, for documents with any link.

    ``lists`` has (key, doc), ``sets`` (doc, hashes) with sorted distinct hashes for all of them; ``docs`` and ``hashes`` bound the blocks of a family.
    """
    links, hangs = None, []

    def of_class(df: DataFrame, doc: str) -> DataFrame:
        """``df`` with the column ``doc`` replaced by what it is known to be connected with."""
        for own, n in hangs:
            own = own.select(F.col("doc").alias(doc), F.col("root").alias("_root"))
            df = df.join(F.broadcast(own) if n <= BROADCAST_PAIRS else own, doc, "left").withColumn(doc, F.coalesce("_root", doc)).drop("_root")
        return df

    def grouped() -> DataFrame:
        """Lists that hold several classes, with their least and greatest member."""
        own = of_class(lists.withColumn("class", F.col("doc")), "class")
        of = own.groupBy("key").agg(
            F.min(F.struct("doc", "class")).alias("first"), F.max(F.struct("doc", "class")).alias("last"),
            F.count(F.lit(1)).alias("members"), F.min("class").alias("a"), F.max("class").alias("z"),
        )
        return own.join(of.where("a <> z").drop("a", "z"), "key")

    for hub in ("first", "last"):
        pairs = grouped().where(F.col("class") != F.col(f"{hub}.class"))
        if hub == "last":  # the least was tried against all
            pairs = pairs.where(F.col("doc") != F.col("first.doc"))
        pairs = pairs.select(F.col(f"{hub}.doc").alias("x"), F.col("doc").alias("y"))
        once = pairs.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.min(F.struct("x", "y")).alias("p"))
        pairs = cut(once.select("p.x", "p.y"))
        rows = pairs.count()
        if not rows:
            continue
        found = cut(verified(few(pairs, rows), sets, rows, percent))
        n = found.count()
        if n:
            found = few(found, n)
            links = found if links is None else links.unionByName(found)
            edges = of_class(of_class(found, "x"), "y").where("x <> y")
            hangs.append((hung(cut(few(edges, n)), n), 2 * n))
    left = cut(grouped().where("members > 3").select("key", "doc", "class", F.col("first.doc").alias("first")))
    rows = left.count()
    if rows:
        found = cut(family_links(left, sets, rows, percent, docs, hashes))
        if not found.isEmpty():
            links = found if links is None else links.unionByName(found)
    if links is None:
        return lists.sparkSession.createDataFrame([], "doc long, class long")
    return components(links).select("doc", F.col("root").alias("class"))
