"""Walks coded with a codebook that no task holds: each shard of walks meets the codes of its own steps only.

A shard is a few walks (about ``STEPS`` steps) as one row of packed columns. Labels are numbered, and steps counted, once per shard: a label
or a transition moves once for each shard that has it, as a part of a packed column, and steps stay packed. Codes are made by parts of the
contexts, each context whole in one task, and go back to the shards in the order in which their transitions came.
Results are those of :func:`codec.encode` and :func:`codec.encode_blocks` with the codebook of :func:`codec.fit`.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.memory import trim, trimmed
from ..plans.session import cut
from . import codec, markov, prefix

#: Steps after which a shard is closed; one walk is never split.
STEPS = 2_000_000
#: Labels, and transitions of shards, that a task numbers or counts.
LABELS, PAIRS = 500_000, 1_500_000
#: Streams that are decoded one by one, as steps for so few cost as much together.
FEW = 16
_MASK = (1 << 64) - 1
_PACKED = "shard long, kind int, part int, n long, a binary, b binary, c binary"


def pack(x: np.ndarray) -> bytes:
    """Integers as compressed planes of bytes."""
    kind = np.min_scalar_type(int(x.max(initial=0))) if x.min(initial=0) >= 0 else np.dtype(np.int64)
    own = np.ascontiguousarray(x.astype(kind)).view(np.uint8).reshape(-1, kind.itemsize).T
    return kind.char.encode() + len(x).to_bytes(8, "little") + pa.compress(np.ascontiguousarray(own).tobytes(), codec="zstd", asbytes=True) if len(x) else b""


def unpack(data: bytes, to=np.int64) -> np.ndarray:
    if not data:
        return np.zeros(0, dtype=to)
    kind, n = np.dtype(data[:1].decode()), int.from_bytes(data[1:9], "little")
    own = np.frombuffer(pa.decompress(data[9:], n * kind.itemsize, codec="zstd", asbytes=True), dtype=np.uint8).reshape(kind.itemsize, n)
    return np.ascontiguousarray(own.T).view(kind).ravel().astype(to)


def _words(labels: pa.Array) -> bytes:
    sink = pa.BufferOutputStream()
    batch = pa.record_batch([labels], names=["label"])
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _row(*row) -> pa.RecordBatch:
    names = [f.strip().split(" ") for f in _PACKED.split(",")]
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    return pa.record_batch([pa.array([x], kinds[k]) for x, (_, k) in zip(row, names, strict=True)], names=[n for n, _ in names])


def _labels(column: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """All labels one after another, and how many each row has; text is cut at blanks and has no empty labels."""
    if pa.types.is_list(column.type):
        return column.flatten(), pc.fill_null(pc.list_value_length(column), 0).to_numpy().astype(np.int64)
    cut_ = pc.split_pattern(pc.fill_null(column, ""), " ")
    flat = cut_.flatten()
    held = pc.not_equal(flat, "")
    so_far = np.concatenate([[0], np.cumsum(held.to_numpy(zero_copy_only=False))])
    ends = np.concatenate([[0], np.cumsum(pc.list_value_length(cut_).to_numpy())])
    return flat.filter(held), np.diff(so_far[ends])


def build(walks: DataFrame, steps: int = STEPS) -> DataFrame:
    """Shards of (path_id, labels), or of (path_id, text) with blanks between labels: paths, their sizes and steps as numbers of the shard's own labels (kind 0), and these labels (kind 3).

    Paths without a label have none. A few hundred thousand labels are unpacked at once, one walk at least.
    """

    def run(batches):
        number = itertools.count(TaskContext.get().partitionId() << 33)

        def close(held):
            paths, sizes, own = zip(*held, strict=True)
            own = pa.chunked_array(own).unify_dictionaries()
            shard, size = next(number), np.concatenate(sizes)
            yield _row(shard, 0, -1, int(size.sum()), pack(np.concatenate(paths)), pack(size), pack(np.concatenate([x.indices.to_numpy() for x in own.chunks])))
            yield _row(shard, 3, -1, len(own.chunk(0).dictionary), _words(own.chunk(0).dictionary), None, None)

        held, n = [], 0
        for b in batches:
            column = b.column(1)
            weight = (pc.binary_length(column) if not pa.types.is_list(column.type) else pc.list_value_length(column)).fill_null(0).to_numpy()
            ends, at, most = np.cumsum(weight), 0, min(steps, 200_000 if pa.types.is_list(column.type) else 1 << 21)
            while at < len(b):
                to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
                flat, sizes = _labels(column.slice(at, to - at))
                some, paths = sizes > 0, b.column(0).slice(at, to - at).to_numpy()
                if some.any():
                    held.append((paths[some], sizes[some], flat.dictionary_encode()))
                    n += len(flat)
                if n >= steps:
                    yield from close(held)
                    held, n = [], 0
                at = to
        if held:
            yield from close(held)

    return walks.select(F.col("path_id").cast("long"), walks.columns[1]).mapInArrow(trimmed(run), _PACKED)


def numbers(shards: DataFrame) -> tuple[DataFrame, int]:
    """Numbers from 0, in label order, of each shard's labels (kind 1: places in the shard, numbers), and how many there are.

    One range shuffle, in which a label has a row for each shard; the driver sees a count per range.
    """
    listed = shards.where("kind = 3")
    n = listed.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]

    def spread(batches):
        for b in batches:
            for shard, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                for own in pa.ipc.open_stream(data):
                    for lo in range(0, len(own), 50_000):
                        label = own.column(0).slice(lo, 50_000)
                        yield pa.record_batch([label, pa.array(np.full(len(label), shard)), pa.array(np.arange(lo, lo + len(label)))], names=["label", "shard", "at"])

    def rank(batches):
        part, last, top, held = TaskContext.get().partitionId(), None, -1, []
        for b in batches:
            label = b.column(0)
            if not len(label):
                continue
            new = np.ones(len(label), dtype=np.int64)
            new[1:] = pc.not_equal(label.slice(1), label.slice(0, len(label) - 1)).to_numpy(zero_copy_only=False)
            new[0] = label[0].as_py() != last
            own = top + np.cumsum(new)
            top, last = int(own[-1]), label[-1].as_py()
            held.append((b.column(1).to_numpy(), b.column(2).to_numpy(), own))
        if held:
            shard, at, own = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.lexsort((at, shard))
            shard, at, own = shard[order], at[order], own[order]
            for lo, hi in _groups(shard):
                yield _row(int(shard[lo]), 1, part, top + 1, pack(np.diff(at[lo:hi], prepend=0)), pack(own[lo:hi]), None)

    each = listed.select("shard", "a").mapInArrow(trimmed(spread), "label string, shard long, at long")
    tasks = max(1, min(-(-n // LABELS) * 2, 100_000), shards.sparkSession.sparkContext.defaultParallelism if n > LABELS else 1)
    ranked = cut(each.repartitionByRange(tasks, "label").sortWithinPartitions("label").mapInArrow(trimmed(rank), _PACKED))
    sizes = sorted((r["part"], r["n"]) for r in ranked.select("part", "n").distinct().collect())
    before = dict(zip([p for p, _ in sizes], itertools.accumulate([0] + [x for _, x in sizes]), strict=False))
    if before:
        start = F.element_at(F.create_map(*(F.lit(x) for p in before.items() for x in p)), F.col("part")).cast("long")
        ranked = ranked.withColumn("n", start)
    return ranked, sum(x for _, x in sizes)


def _groups(key: np.ndarray):
    """(begin, end) of each stretch of equal keys."""
    at = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, dtype=np.int64)
    return zip(at.tolist(), [*at[1:].tolist(), len(key)], strict=True)


def _together(*frames: DataFrame, tasks: int, by: str = "shard") -> DataFrame:
    both = frames[0]
    for other in frames[1:]:
        both = both.unionByName(other)
    return both.repartition(tasks, by).sortWithinPartitions(by, "kind")


def _each(batches):
    """(first column, rows of the other columns) of each group of equal first columns, which come one after another."""
    rows = (row for b in batches for row in zip(*(c.to_pylist() for c in b.columns), strict=True))
    for key, own in itertools.groupby(rows, lambda r: r[0]):
        yield key, [r[1:] for r in own]


class Shard:
    """Walks of a shard, their steps as numbers of its transitions, and these as (ctx, sym), in the order of both."""

    def __init__(self, rows: list[tuple]):
        """From packed rows without their shard: steps (kind 0) and numbers of labels (kind 1)."""
        (steps,) = (r for r in rows if r[0] == 0)
        self.paths, self.sizes, local = unpack(steps[3]), unpack(steps[4]), unpack(steps[5], np.int32)
        node = np.zeros(int(local.max(initial=-1)) + 1, dtype=np.int64)
        for r in rows:
            if r[0] == 1:
                node[np.cumsum(unpack(r[3]))] = unpack(r[4]) + r[2]
        self.ends = np.cumsum(self.sizes + 1)  # an end symbol for each walk
        inner = np.ones(len(local) + len(self.sizes), dtype=bool)
        inner[self.ends - 1] = False
        wide = int(node.max(initial=0)) + 4
        key = np.full(len(inner), (markov.START + 3) * wide, dtype=np.int64)  # few arrays of the length of all steps are held at once
        key[1:][inner[:-1]] = ((node + 3) * wide)[local]
        key[~inner] += markov.STOP + 3
        key[inner] += (node + 3)[local]
        del local
        order = np.argsort(key)
        key = key[order]
        new = np.ones(len(key), dtype=bool)
        new[1:] = key[1:] != key[:-1]
        first = np.flatnonzero(new)
        self.steps = np.empty(len(key), dtype=np.int32)
        self.steps[order] = np.cumsum(new, dtype=np.int32) - 1
        self.n = np.diff(first, append=len(key))
        key = key[first]
        self.ctx, self.sym = key // wide - 3, key % wide - 3

    def part(self, parts: int) -> np.ndarray:
        return ((self.ctx.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % parts


def _pieces(parts: int):
    def run(batches):
        for shard, rows in _each(batches):
            own = Shard(rows)
            del rows
            at = own.part(parts)
            order = np.argsort(at, kind="stable")
            for lo, hi in _groups(at[order]):
                i = order[lo:hi]
                yield _row(shard, 0, int(at[i[0]]), hi - lo, pack(np.diff(own.ctx[i] + 3, prepend=0)), pack(own.sym[i] + 3), pack(own.n[i]))

    return run


def huffman(profile: list[float]) -> list[int]:
    """Lengths like those of :func:`prefix.huffman`, from two queues, for two ascending whole weights or more.

    Merged weights never fall, and those that are equal come from equal weights in the order of their ranks. What was merged has smaller ranks than the leaves that are left, so it goes first among equals.
    """
    n = len(profile)
    w, above, i, j = [*profile, *[0.0] * (n - 1)], [0] * (2 * n - 1), 0, n
    for node in range(n, 2 * n - 1):
        if j < node and (i >= n or w[j] <= w[i]):
            a, j = j, j + 1
        else:
            a, i = i, i + 1
        if j < node and (i >= n or w[j] <= w[i]):
            b, j = j, j + 1
        else:
            b, i = i, i + 1
        w[node] = w[a] + w[b]
        above[a] = above[b] = node
    depth = [0] * (2 * n - 1)
    for node in range(2 * n - 3, -1, -1):
        depth[node] = depth[above[node]] + 1
    return depth[:n]


def book(ctx: np.ndarray, sym: np.ndarray, n: np.ndarray, alpha: float = 1.0, force_stop: bool = True, single: str = "empty", cache: dict | None = None):
    """(ctx, sym, size, value) of whole contexts of counted transitions, which may repeat, in the order of ctx and sym: the codes of :func:`codec.fit_counts`."""
    cache, make = {} if cache is None else cache, huffman if float(alpha).is_integer() else prefix.huffman
    if force_stop:
        every = np.unique(ctx)
        ctx, sym, n = np.concatenate([ctx, every]), np.concatenate([sym, np.full(len(every), markov.STOP)]), np.concatenate([n, np.zeros(len(every), dtype=np.int64)])
    order = np.argsort((ctx + 3) * (int(sym.max(initial=0)) + 4) + sym + 3)
    ctx, sym, n = ctx[order], sym[order], n[order]
    first = np.flatnonzero(np.r_[True, (ctx[1:] != ctx[:-1]) | (sym[1:] != sym[:-1])][: len(ctx)])
    ctx, sym, w = ctx[first], sym[first], np.add.reduceat(n, first) + float(alpha) if len(first) else n + float(alpha)
    group = np.cumsum(np.r_[True, ctx[1:] != ctx[:-1]][: len(ctx)])
    whole = float(alpha).is_integer() and w.max(initial=0) < 1 << 31  # then one sort does for both
    order = np.argsort(group << 32 | w.astype(np.int64), kind="stable") if whole else np.lexsort((w, group))  # by weight, then symbol
    weight, begin = w[order], np.flatnonzero(np.diff(group, prepend=0))  # equal contexts keep their places
    many = np.diff(np.append(begin, len(ctx)))
    size = np.ones(len(ctx), dtype=np.int64)
    if single == "empty":
        size[begin[many == 1]] = 0
    for lo, k in zip(begin[many > 2].tolist(), many[many > 2].tolist(), strict=True):
        own = weight[lo : lo + k]
        key = own.tobytes() if k <= 32 else None
        got = cache.get(key)
        if got is None:
            got = np.array(make(own.tolist()), dtype=np.int64)
            if key is not None and len(cache) < 200_000:
                cache[key] = got
        size[lo : lo + k] = got
    if size.max(initial=0) > 52:
        raise ValueError("code longer than 52 bits")
    again = np.argsort(group << 6 | size, kind="stable")
    share = np.uint64(1) << (52 - size[again]).astype(np.uint64)
    before = np.cumsum(share, dtype=np.uint64) - share  # wraps, but differences within a context do not
    before -= np.repeat(before[begin], many)
    out_size, out_value = np.zeros(len(ctx), dtype=np.int64), np.zeros(len(ctx), dtype=np.int64)
    place = order[again]
    out_size[place], out_value[place] = size[again], (before >> (52 - size[again]).astype(np.uint64)).astype(np.int64)
    return ctx, sym, out_size, out_value


def _code(alpha: float, force_stop: bool):
    def contexts(row):
        return np.cumsum(unpack(row[1])) - 3

    def symbols(row):
        return unpack(row[2]) - 3

    def counts(row):
        return unpack(row[3])

    def run(batches):
        cache: dict = {}
        for part, rows in _each(batches):
            of_ctx, of_sym, size, value = book(*(np.concatenate([x(r) for r in rows]) for x in (contexts, symbols, counts)), alpha, force_stop, cache=cache)
            wide = int(max(of_sym.max(initial=0), 0)) + 4
            key = (of_ctx + 3) * wide + of_sym + 3
            del of_ctx, of_sym
            for r in rows:
                at = np.searchsorted(key, (contexts(r) + 3) * wide + symbols(r) + 3)
                yield _row(r[0], 2, part, len(at), pack(size[at]), pack(value[at]), None)
            del key, size, value, rows
            trim()

    return run


def encode(walks: DataFrame, block: int | None = None, alpha: float = 1.0, force_stop: bool = True) -> DataFrame:
    """(shard, path_id, block_no, entry_ctx, first_seq, n_symbols, n_bits, bits, book) of (path_id, labels).

    Before the walks of a shard, or their blocks of ``block`` symbols, comes a row with its part of the codebook; others have none.
    """
    spark = walks.sparkSession
    shards = cut(build(walks))
    total, many = shards.where("kind = 0").agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    ranked, _ = numbers(shards)
    tasks = max(1, min(2 * many, max(many, 4 * spark.sparkContext.defaultParallelism)))
    parts = max(1, total // PAIRS)
    steps = shards.where("kind = 0")
    pieces = _together(steps, ranked, tasks=tasks).mapInArrow(trimmed(_pieces(parts)), _PACKED)
    codes = cut(pieces.repartition(parts, "part").sortWithinPartitions("part", "shard").select("part", "shard", "a", "b", "c").mapInArrow(trimmed(_code(alpha, force_stop)), _PACKED))
    return _together(steps, ranked, codes, tasks=tasks).mapInArrow(trimmed(_bits(parts, block)), _CODED)


_CODED = "shard long, path_id long, block_no long, entry_ctx long, first_seq long, n_symbols long, n_bits long, bits binary, book binary"


def joined(value: np.ndarray, size: np.ndarray, place: np.ndarray, width: int) -> bytes:
    """``width`` bits with each value, of ``size`` bits, at its place; places ascend. Work follows the values, not their bits."""
    out, value = np.zeros(width // 64 + 2, dtype=np.uint64), value.view(np.uint64)
    word, over = place >> 6, (place & 63) + size - 64  # bits beyond the word's end
    own = value >> np.maximum(over, 0).view(np.uint64) << np.maximum(-over, 0).view(np.uint64)
    first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
    out[word[first]] = np.add.reduceat(own, first)
    cut_ = np.flatnonzero(over > 0)  # one at most at each word's end
    out[word[cut_] + 1] += value[cut_] << (64 - over[cut_]).view(np.uint64)
    return out.astype(">u8").tobytes()[: width // 8]


def _bits(parts: int, block: int | None):
    def run(batches):
        for shard, rows in _each(batches):
            own = Shard([r for r in rows if r[0] < 2])
            at, size, value = own.part(parts), np.zeros(len(own.ctx), dtype=np.uint8), np.zeros(len(own.ctx), dtype=np.int64)
            for r in rows:
                if r[0] == 2:
                    mine = at == r[1]
                    size[mine], value[mine] = unpack(r[3], np.uint8), unpack(r[4])
            del rows, at
            held = [pack(x) for x in (np.diff(own.ctx + 3, prepend=0), own.sym + 3, size, value)]
            yield _coded([shard], [None] * 6, pa.array([None], pa.binary()), pa.array([b"".join(len(x).to_bytes(8, "little") + x for x in held)], pa.binary()))
            ends = own.ends
            if block is None:
                lo, path, number = np.r_[0, ends[:-1]], own.paths, np.zeros(len(ends), dtype=np.int64)
                first = number
            else:
                many = -(-(own.sizes + 1) // block)
                number = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                path, first = np.repeat(own.paths, many), number * block
                lo = np.repeat(np.r_[0, ends[:-1]], many) + first
            hi = np.append(lo[1:], ends[-1])
            entry = own.ctx[own.steps[lo]]
            so_far = np.zeros(len(own.steps) + 1, dtype=np.int64)
            np.cumsum(size[own.steps], out=so_far[1:])
            bits = so_far[hi] - so_far[lo]
            at = 0
            while at < len(lo):  # some ten thousand symbols at once, one walk at least
                to = min(max(at + 1, int(np.searchsorted(lo, lo[at] + 50_000))), at + 5_000)
                part, base = own.steps[lo[at] : hi[to - 1]], so_far[lo[at]]
                width = -(-bits[at:to] // 8) * 8  # each begins a byte
                begin = np.cumsum(width) - width
                place = so_far[lo[at] : hi[to - 1]] - base + np.repeat(begin - (so_far[lo[at:to]] - base), hi[at:to] - lo[at:to])
                data = joined(value[part], size[part].astype(np.int64), place, int(width.sum()))
                cuts = np.append(begin, width.sum()) // 8
                bytes_ = pa.Array.from_buffers(pa.binary(), to - at, [None, pa.py_buffer(cuts.astype(np.int32)), pa.py_buffer(data)])
                yield _coded(np.full(to - at, shard), [path[at:to], number[at:to], entry[at:to], first[at:to], (hi - lo)[at:to], bits[at:to]], bytes_, pa.nulls(to - at, pa.binary()))
                at = to

    return run


def _coded(shard, longs, bits, held) -> pa.RecordBatch:
    none = len(longs) and longs[0] is None
    columns = [pa.array([None], pa.int64()) if none else pa.array(x, pa.int64()) for x in longs]
    return pa.record_batch([pa.array(shard, pa.int64()), *columns, bits, held], names=[f.strip().split(" ")[0] for f in _CODED.split(",")])


class Together:
    """Decodes many streams step by step at once. ``packed`` (ctx, sym, size, value) may lack codes that no stream has: codes are free of prefixes, so the others stay as they are."""

    def __init__(self, packed):
        ctx, sym, size, value = packed
        self.long = max(1, int(size.max(initial=0)))
        start = value << (self.long - size)
        order = np.lexsort((start, ctx))
        ctx, sym, size, start = ctx[order], sym[order], size[order], start[order]
        self.known = np.unique(ctx)
        self.alone = codec.Decoder([ctx, sym, size, value[order]]) if len(self.known) >> (62 - self.long) else None  # keys of so long codes have no room
        if self.alone:
            return
        key = np.searchsorted(self.known, ctx) << self.long | start
        none = np.array([-(1 << 62)])  # found where no code is
        self.key, self.until = np.concatenate([none, key]), np.concatenate([none, key + (np.int64(1) << (self.long - size))])
        self.sym, self.size = np.concatenate([[markov.ESC], sym]), np.concatenate([[0], size])
        self.next = np.concatenate([[-1], self.rows(sym)])
        begin = np.flatnonzero(np.r_[True, ctx[1:] != ctx[:-1]][: len(ctx)])
        self.longest = np.maximum.reduceat(size, begin) if len(begin) else size

    def rows(self, ctx: np.ndarray) -> np.ndarray:
        """First key of each context, -1 if it has no code."""
        if not len(self.known):
            return np.full(len(ctx), -1)
        at = np.minimum(np.searchsorted(self.known, ctx), len(self.known) - 1)
        return np.where(self.known[at] == ctx, at << self.long, -1)

    def _alone(self, ctx, most, n_bits, data):
        out, names = [], _STATUS.tolist()
        for i, own in enumerate(zip(data.to_pylist(), n_bits.tolist(), ctx.tolist(), most.tolist(), strict=True)):
            for k, (_, _, x, _) in zip(range(own[3]), self.alone.steps(own[0] or b"", *own[1:]), strict=False):
                out.append((i, k, markov.ESC, names.index(x)) if isinstance(x, str) else (i, k, x, 0))
        return tuple(np.array(out, dtype=np.int64).reshape(-1, 4).T)

    def _why(self, want: int, begin: int, end: int) -> int:
        return 2 if want >= 0 and begin + int(self.longest[want >> self.long]) > end else 1

    def decode(self, ctx: np.ndarray, most: np.ndarray, n_bits: np.ndarray, data: pa.Array):
        """(stream, step, symbol, status) by stream and step: symbols up to ``most`` of each or its end symbol; status (0, or 1: invalid_prefix, 2: truncated) is the last step of a stream that fails.

        Streams go on together, the last few of them one by one. Status 3 is escape_unsupported.
        """
        if self.alone:
            return self._alone(ctx, most, n_bits, data)
        offsets = np.frombuffer(data.buffers()[1], dtype=np.int32)[data.offset : data.offset + len(data) + 1].astype(np.int64)
        raw = np.frombuffer(data.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
        raw = np.concatenate([raw, np.zeros(8, dtype=np.uint8)])
        words = np.zeros(len(raw) - 7, dtype=np.uint64)
        for i in range(8):
            words |= raw[i : len(words) + i].astype(np.uint64) << np.uint64(56 - 8 * i)
        base, out = np.cumsum(most) - most, np.full(int(most.sum()), markov.ESC, dtype=np.int64)
        done, status = np.zeros(len(most), dtype=np.int64), np.zeros(len(most), dtype=np.int64)
        act = np.argsort(-most, kind="stable")
        act = act[most[act] > 0]
        row, pos, k, shift = self.rows(ctx[act]), (offsets[:-1][act] - offsets[0]) * 8, 0, np.uint64(64 - self.long)
        end, left, to = pos + n_bits[act], most[act], base[act]
        key, until, sizes, syms, follow = self.key, self.until, self.size, self.sym, self.next
        while len(act) > FEW:
            window = (words[pos >> 3] << (pos & 7).view(np.uint64) >> shift).view(np.int64)
            want = np.where(row < 0, -1, row | window)
            at = key.searchsorted(want, "right") - 1
            fits, was = until[at] > want, pos
            pos = pos + sizes[at]
            fits &= pos <= end
            sym, row = syms[at], follow[at]
            out[to + k] = sym
            k += 1
            if left[-1] > k and fits.all() and sym.min() >= 0:
                continue
            lost = ~fits
            status[act[lost]] = [self._why(*x) for x in zip(want[lost].tolist(), was[lost].tolist(), end[lost].tolist(), strict=True)]
            status[act[fits & (sym == markov.ESC)]] = 3
            go = fits & (sym >= 0) & (left > k)
            done[act[~go]] = k
            act, pos, end, left, to, row = act[go], pos[go], end[go], left[go], to[go], row[go]
        for i, r, p, z, n, t in zip(act.tolist(), row.tolist(), pos.tolist(), end.tolist(), left.tolist(), to.tolist(), strict=True):
            j, line = k, words.data
            while j < n:
                want = -1 if r < 0 else r | ((line[p >> 3] << (p & 7)) & _MASK) >> (64 - self.long)
                at = int(key.searchsorted(want, "right")) - 1
                begin, p = p, p + int(sizes[at])
                sym = int(syms[at])
                out[t + j] = sym
                j += 1
                if until[at] <= want or p > z:
                    status[i] = self._why(want, begin, z)
                    break
                if sym < 0:
                    status[i] = 3 * (sym == markov.ESC)
                    break
                r = int(follow[at])
            done[i] = j
        stream = np.repeat(np.arange(len(most)), done)
        step = np.arange(done.sum()) - np.repeat(np.cumsum(done) - done, done)
        bad = (status[stream] > 0) & (step == done[stream] - 1)
        return stream, step, out[base[stream] + step], np.where(bad, status[stream], 0)


_STATUS = np.array(["ok", "invalid_prefix", "truncated", "escape_unsupported"], dtype=object)


def rows_of(decoder: Together, path, ctx, first, most, n_bits, data):
    """Batches (path_id, seq, node, status) of streams; an end symbol gives no row."""
    edges, at = np.cumsum(most), 0
    while at < len(most):
        to = max(at + 1, int(np.searchsorted(edges, (edges[at - 1] if at else 0) + 4_000_000, "right")))
        stream, step, node, status = decoder.decode(ctx[at:to], most[at:to], n_bits[at:to], data.slice(at, to - at))
        shown = np.flatnonzero((node != markov.STOP) | (status > 0))
        for lo in range(0, len(shown), 100_000):
            i = shown[lo : lo + 100_000]
            lost = status[i] > 0
            said = pa.array(_STATUS[status[i]], pa.string()) if lost.any() else pa.repeat(pa.scalar("ok"), len(i))
            yield pa.record_batch([pa.array(path[at:to][stream[i]]), pa.array(first[at:to][stream[i]] + step[i]), pa.array(node[i], mask=lost), said], names=["path_id", "seq", "node", "status"])
        at = to


def decode(encoded: DataFrame) -> DataFrame:
    """(path_id, seq, node, status) of what :func:`encode` gives, from its bits and its parts of the codebook alone; an error is a last row without node."""

    def run(batches):
        decoder = None
        for b in batches:
            cuts = [i for i, x in enumerate(b.column(8).is_valid().to_pylist()) if x]
            for lo, hi in zip([0, *cuts], [*cuts, len(b)], strict=True):
                own = b.slice(lo, hi - lo)
                if lo in cuts and len(own):
                    data, packed = own.column(8)[0].as_py(), []
                    while data:
                        size = int.from_bytes(data[:8], "little")
                        packed.append(unpack(data[8 : 8 + size]))
                        data = data[8 + size :]
                    decoder, own = Together([np.cumsum(packed[0]) - 3, packed[1] - 3, *packed[2:]]), own.slice(1)
                if len(own):
                    path, _, ctx, first, most, n_bits = (own.column(i).to_numpy() for i in range(1, 7))
                    yield from rows_of(decoder, path, ctx, first, most, n_bits, own.column(7))

    return encoded.mapInArrow(trimmed(run), "path_id long, seq long, node long, status string")
