"""Lossless coding of walks with a codebook: whole walks, blocks, partial decoding, errors, round trip, storage."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.session import cut
from . import markov, prefix

#: Largest codebook (25 bytes a row, packed) that decoders get by broadcast.
BROADCAST_ROWS = 8_000_000
#: Largest codebook (under 100 bytes a row) that encoders get by broadcast; a larger one is joined by a shuffle, of which hot transitions are split at run time.
ENCODER_ROWS = 1_000_000
#: Code rows of contexts that a decoder keeps unpacked.
UNPACKED_ROWS = 500_000
#: Symbols after which a decoder gives up.
MAX_SYMBOLS = 100_000_000


@F.pandas_udf(T.BinaryType())
def pack_bits(bits: pd.Series) -> pd.Series:
    """Bits as text, first bit highest, padded with zeros to whole bytes."""
    return bits.map(lambda b: int(b.ljust(-(-len(b) // 8) * 8, "0"), 2).to_bytes(-(-len(b) // 8), "big") if b else b"")


def _coded(paths: DataFrame, codebook: DataFrame, escape: str = "off", width: int = 0) -> DataFrame:
    codes = codebook.select("ctx", "sym", "code")
    if codebook.limit(ENCODER_ROWS + 1).count() <= ENCODER_ROWS:  # no step moves for its code
        codes = F.broadcast(codes)
    steps = markov.transitions(paths).join(codes, ["ctx", "sym"], "left")
    if escape == "literal":  # an unseen node as the escape code and its number
        esc = codebook.where(F.col("sym") == markov.ESC).select("ctx", F.col("code").alias("_esc"))
        literal = F.when(F.col("sym") >= 0, F.concat("_esc", F.lpad(F.bin("sym"), width, "0")))
        steps = steps.join(esc, "ctx", "left").withColumn("code", F.coalesce("code", literal)).drop("_esc")
    return steps


def encode(paths: DataFrame, codebook: DataFrame, on_unseen: str = "null", escape: str = "off", width: int = 0) -> DataFrame:
    """(path_id, n_symbols, n_bits, bits, status) of (path_id, nodes); 'unseen' paths have no bits, or are an error with ``on_unseen='error'``."""
    own = _coded(paths, codebook, escape, width).groupBy("path_id").agg(
        F.array_sort(F.collect_list(F.struct("seq", F.coalesce("code", F.lit("")).alias("code")))).alias("c"), F.max(F.col("code").isNull()).alias("bad")
    )
    text = F.array_join(F.transform("c", lambda x: x["code"]), "")
    status = F.when(F.col("bad"), F.raise_error("unseen transition").cast("string") if on_unseen == "error" else F.lit("unseen")).otherwise("ok")
    out = own.select("path_id", F.size("c").cast("long").alias("n_symbols"), F.when(~F.col("bad"), text).alias("t"), status.alias("status"))
    return out.select("path_id", "n_symbols", F.length("t").cast("long").alias("n_bits"), F.when(F.col("t").isNotNull(), pack_bits(F.coalesce("t", F.lit("")))).alias("bits"), "status")


def encode_blocks(paths: DataFrame, codebook: DataFrame, block: int = 4096) -> DataFrame:
    """(path_id, block_no, entry_ctx, first_seq, n_symbols, bit_offset, n_bits, bits): blocks that decode alone.

    No block holds more than ``block`` symbols, however long its walk is.
    """
    steps = _coded(paths, codebook).withColumn("block_no", F.floor(F.col("seq") / block).cast("long"))
    own = steps.groupBy("path_id", "block_no").agg(F.array_sort(F.collect_list(F.struct("seq", "ctx", "code"))).alias("c"))
    text = F.array_join(F.transform("c", lambda x: x["code"]), "")
    out = own.select("path_id", "block_no", F.get("c", F.lit(0))["ctx"].alias("entry_ctx"), F.get("c", F.lit(0))["seq"].alias("first_seq"), F.size("c").cast("long").alias("n_symbols"), text.alias("t"))
    before = Window.partitionBy("path_id").orderBy("block_no").rowsBetween(Window.unboundedPreceding, -1)
    bits = F.length("t").cast("long")
    return out.select("path_id", "block_no", "entry_ctx", "first_seq", "n_symbols", F.coalesce(F.sum(bits).over(before), F.lit(0)).alias("bit_offset"), bits.alias("n_bits"), pack_bits("t").alias("bits"))


class Encoder:
    """Codes of a packed book, looked up for all steps of a path at once."""

    def __init__(self, packed):
        ctx, sym, size, value = packed
        order = np.lexsort((sym, ctx))
        self.size, self.value = size[order].astype(np.int64), value[order]
        self.low = min(int(sym.min(initial=0)), markov.ESC)
        self.wide = int(max(sym.max(initial=0), ctx.max(initial=0))) - self.low + 1
        self.key = (ctx[order] - self.low) * self.wide + sym[order] - self.low

    def places(self, ctx: np.ndarray, sym: np.ndarray) -> np.ndarray:
        """Places of the codes of steps, -1 for one that is unseen."""
        if not len(self.key):
            return np.full(len(ctx), -1, dtype=np.int64)
        key = (ctx - self.low) * self.wide + sym - self.low
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        inside = (np.minimum(ctx, sym) >= self.low) & (np.maximum(ctx, sym) - self.low < self.wide)
        return np.where(inside & (self.key[at] == key), at, -1)

    def sizes(self, at: np.ndarray) -> np.ndarray:
        """Bits of the codes at these places, none of an unseen step."""
        return np.append(self.size, 0)[at]

    def codes(self, nodes: np.ndarray) -> np.ndarray | None:
        """Places of the codes of a path's steps, its end included; None if one is unseen."""
        at = self.places(np.concatenate([[markov.START], nodes]), np.concatenate([nodes, [markov.STOP]]))
        return None if (at < 0).any() else at

    def bits(self, at: np.ndarray) -> np.ndarray:
        """The bits of these codes, one after another."""
        size = self.size[at]
        left = np.repeat(np.cumsum(size), size) - np.arange(size.sum()) - 1  # bits of the same code that follow
        return (np.repeat(self.value[at], size) >> left & 1).astype(np.uint8)


def _listed(row, spine) -> np.ndarray:
    """Nodes of a path: as they are, or an alternative (null at the begin) and a stretch of the spine for each run."""
    if spine is None:
        return np.array(row[0], dtype=np.int64)
    parts = [x for a, f, z in zip(*row, strict=True) for x in ([] if a is None else [[a]]) + [spine[f : z + 1]]]
    return np.concatenate([np.zeros(0, dtype=np.int64), *parts])


class Line:
    """The codes of the steps along a spine, one after another: the bits of a stretch of it are copied, and only steps that touch something else are looked up."""

    def __init__(self, encoder: Encoder, spine: np.ndarray):
        at = encoder.places(spine[:-1], spine[1:])
        self.encoder, self.spine = encoder, spine
        self.lost = np.concatenate([[0], np.cumsum(at < 0)])
        self.ends = np.concatenate([[0], np.cumsum(encoder.sizes(at))])
        self.bits = encoder.bits(at[at >= 0])

    def coded(self, batch: pa.RecordBatch):
        """(first path, number of paths, symbols of each, bits of each, whether each is known, bytes of all) of some paths of runs (path_id, heads, firsts, lasts) at once.

        A path is a row of elements: alternatives, stretches and its end. An element is the code of the step that enters it, then the bits within it.
        """
        runs = pc.list_value_length(batch.column(1)).to_numpy().astype(np.int64)
        head, first, last = (c.flatten() for c in batch.columns[1:])
        named, head = head.is_valid().to_numpy(zero_copy_only=False), head.fill_null(0).to_numpy()
        first, last = first.to_numpy(), np.minimum(last.to_numpy(), len(self.spine) - 1)
        held = first <= last
        a, z = np.where(held, first, 0), np.where(held, last, 0)
        if not len(self.spine):
            into = leave = z
        else:
            into, leave = self.spine[a], self.spine[z]
        some = np.stack([named, held], axis=1)
        path = np.repeat(np.repeat(np.arange(len(runs)), runs), 2)[some.ravel()]
        stops = np.cumsum(np.bincount(path, minlength=len(runs)))  # each path has one element more, its end

        def each(alt, stretch, stop):
            return np.insert(np.stack([np.broadcast_to(alt, len(head)), stretch], axis=1)[some], stops, stop)

        enter, leave = each(head, into, markov.STOP), each(head, leave, markov.STOP)
        n, begin = each(1, z - a + 1, 1), each(0, self.ends[a], 0)
        inner, lost = each(0, self.ends[z] - self.ends[a], 0), each(0, self.lost[z] - self.lost[a], 0)
        stops += np.arange(len(runs))
        starts = np.append(0, stops[:-1] + 1)
        before = np.append(markov.START, leave[:-1])
        before[starts] = markov.START
        at = self.encoder.places(before, enter)
        known = np.add.reduceat(lost + (at < 0), starts) == 0
        keep = np.repeat(known, stops - starts + 1)
        code, inner = np.where(keep, self.encoder.sizes(at), 0), np.where(keep, inner, 0)
        width = np.add.reduceat(code + inner, starts)
        symbols, room = np.add.reduceat(n, starts), -(-width // 8) * 8
        ends, lo = np.cumsum(room), 0
        while lo < len(runs):  # about 2 MB at once, one path at least
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + (1 << 24), "right")))
            part = slice(starts[lo], stops[hi - 1] + 1)
            size, within = code[part], inner[part]
            place = np.cumsum(size + within) - size - within  # in a row, then each path from its byte on
            place += np.repeat((ends - room - np.cumsum(width) + width)[lo:hi], (stops - starts + 1)[lo:hi]) - (ends - room - np.cumsum(width) + width)[lo]
            out = np.zeros(int(room[lo:hi].sum()), dtype=np.uint8)
            out[np.repeat(place - np.cumsum(size) + size, size) + np.arange(size.sum())] = self.encoder.bits(at[part][size > 0])
            long = np.flatnonzero(within)
            for to, x, k in zip((place + size)[long].tolist(), begin[part][long].tolist(), within[long].tolist(), strict=True):
                out[to : to + k] = self.bits[x : x + k]
            yield lo, hi - lo, symbols[lo:hi], width[lo:hi], known[lo:hi], np.packbits(out)
            lo = hi


def listed(paths: DataFrame, spine: np.ndarray) -> DataFrame:
    """(path_id, nodes) of a few paths of runs."""
    line = paths.sparkSession.sparkContext.broadcast(spine)

    def run(batches):
        for b in batches:
            for path, *row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                yield pa.record_batch([pa.array([path], pa.int64()), pa.array([_listed(row, line.value)], pa.list_(pa.int64()))], names=["path_id", "nodes"])

    return paths.select("path_id", "heads", "firsts", "lasts").mapInArrow(run, "path_id long, nodes array<long>")


def expand_by_row(paths: DataFrame, edges: DataFrame, index: DataFrame, spine: np.ndarray) -> DataFrame:
    """(path_id, labels, ok) of paths of runs, as :func:`normalize.expand_edges` has them of their edge ids, labels joined by commas, without a shuffle of steps.

    Each path becomes ids of ``edges`` (src, dst, edge_id), and these its labels. A path without an edge gives no row. Edges and the
    index of their labels are broadcast; the caller checks their size.
    """
    src, dst = (index.select(F.col("label").alias(x), F.col("idx").alias(f"_{x}")) for x in ("src", "dst"))
    got = edges.join(src, "src").join(dst, "dst").select("edge_id", "_src", "_dst").toArrow()
    own = [c.to_numpy() for c in got.columns]
    order = np.argsort(own[0])
    labels = index.orderBy("idx").select("label").toArrow().column(0).combine_chunks()
    sent = paths.sparkSession.sparkContext.broadcast(([c[order] for c in own], labels, spine))

    def run(batches):
        (ids, src_of, dst_of), names, line = sent.value
        wide = len(names) + 16
        by_ends = np.argsort(src_of * wide + dst_of)
        key = (src_of * wide + dst_of)[by_ends]
        for b in batches:
            for path, *row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                nodes = _listed(row, line)
                if len(nodes) < 2 or not len(ids):
                    continue
                step = nodes[:-1] * wide + nodes[1:]
                at = np.minimum(np.searchsorted(key, step), len(key) - 1)
                known = key[at] == step
                edge_ids = np.where(known, ids[by_ends[at]], 0)
                place = np.searchsorted(ids, edge_ids[known])
                a, z = src_of[place], dst_of[place]
                ok = bool(known.all() and (z[:-1] == a[1:]).all())
                text = ",".join(names.take(pa.array(np.concatenate([a[:1], z]))).to_pylist())
                yield pa.record_batch([pa.array([path], pa.int64()), pa.array([text], pa.string()), pa.array([ok])], names=["path_id", "labels", "ok"])

    return paths.select("path_id", "heads", "firsts", "lasts").mapInArrow(run, "path_id long, labels string, ok boolean")


def _by_row(paths: DataFrame, codebook: DataFrame, spine, schema: str, make) -> DataFrame:
    """Rows that ``make`` gives for the nodes of each path, without a shuffle of steps."""
    sent = _decoder(codebook)
    line = None if spine is None else paths.sparkSession.sparkContext.broadcast(spine)

    def run(batches):
        encoder = Encoder(sent.value[0])
        for b in batches:
            out, held = [], 0
            for path, *row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                for made in make(encoder, path, _listed(row, line and line.value)):
                    out.append(made)
                    held += 64 + len(made[-1] or b"") if isinstance(made[-1], bytes | None) else 64
                    if held > 1 << 23:
                        yield _batch(out, schema)
                        out, held = [], 0
            if out:
                yield _batch(out, schema)

    columns = ["nodes"] if spine is None else ["heads", "firsts", "lasts"]
    return paths.select("path_id", *columns).mapInArrow(run, schema)


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    fields = [f.strip().split(" ") for f in schema.split(",")]
    return pa.record_batch([pa.array(c, kinds[k]) for c, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def encode_by_row(paths: DataFrame, codebook: DataFrame, spine: np.ndarray | None = None) -> DataFrame:
    """(path_id, n_symbols, n_bits, status, bits) like :func:`encode`, path by path, with the codebook as a broadcast of a checked size.

    Paths are (path_id, nodes), or runs (path_id, heads, firsts, lasts) over ``spine``, the nodes of all segments.
    """

    def make(encoder, path, nodes):
        at = encoder.codes(nodes)
        if at is None:
            return [(path, len(nodes) + 1, None, "unseen", None)]
        bits = encoder.bits(at)
        return [(path, len(nodes) + 1, len(bits), "ok", np.packbits(bits).tobytes())]

    schema = "path_id long, n_symbols long, n_bits long, status string, bits binary"
    if spine is None:
        return _by_row(paths, codebook, None, schema, make)
    sent = _decoder(codebook)
    line = paths.sparkSession.sparkContext.broadcast(spine)

    def run(batches):
        coder = Line(Encoder(sent.value[0]), line.value)
        for b in batches:
            for lo, k, symbols, width, known, data in coder.coded(b) if len(b) else ():
                offsets = np.append(0, np.cumsum(-(-width // 8))).astype(np.int32)
                valid = None if known.all() else pa.py_buffer(np.packbits(known, bitorder="little"))
                bits = pa.Array.from_buffers(pa.binary(), k, [valid, pa.py_buffer(offsets), pa.py_buffer(data)])
                status = pa.array(np.where(known, "ok", "unseen"), pa.string())
                yield pa.record_batch([b.column(0).slice(lo, k), pa.array(symbols), pa.array(width, mask=~known), status, bits], names=["path_id", "n_symbols", "n_bits", "status", "bits"])

    return paths.select("path_id", "heads", "firsts", "lasts").mapInArrow(run, schema)


def encode_blocks_by_row(paths: DataFrame, codebook: DataFrame, block: int = 4096, spine: np.ndarray | None = None) -> DataFrame:
    """Blocks like those of :func:`encode_blocks`, path by path; an unseen step is an error."""

    def make(encoder, path, nodes):
        at = encoder.codes(nodes)
        if at is None:
            raise ValueError(f"unseen transition in path {path}")
        bits = encoder.bits(at)
        ends = np.concatenate([[0], np.cumsum(encoder.size[at])])
        for number, lo in enumerate(range(0, len(at), block)):
            hi = min(lo + block, len(at))
            a, z = int(ends[lo]), int(ends[hi])
            yield path, number, int(nodes[lo - 1]) if lo else markov.START, lo, hi - lo, a, z - a, np.packbits(bits[a:z]).tobytes()

    return _by_row(paths, codebook, spine, "path_id long, block_no long, entry_ctx long, first_seq long, n_symbols long, bit_offset long, n_bits long, bits binary", make)


class Decoder:
    """Tries of all contexts as maps from bits so far to a symbol, unpacked when a context is first met."""

    def __init__(self, packed, escape: str = "off", width: int = 0):
        self.ctx, self.sym, self.size, self.value = packed  # in the order of ctx
        self.codes: dict[int, dict[str, int]] = {}
        self.longest: dict[int, int] = {}
        self.held, self.line = 0, None
        self.escape, self.width = escape, width

    def of(self, ctx: int) -> dict[str, int] | None:
        own = self.codes.get(ctx)
        if own is None:
            lo, hi = np.searchsorted(self.ctx, [ctx, ctx + 1]).tolist()
            if lo == hi:
                return None
            if self.held > UNPACKED_ROWS:
                self.codes, self.longest, self.held = {}, {}, 0
            rows = zip(self.sym[lo:hi].tolist(), self.size[lo:hi].tolist(), self.value[lo:hi].tolist(), strict=True)
            own = self.codes[ctx] = {f"{v:0{n}b}" if n else "": x for x, n, v in rows}
            self.longest[ctx], self.held = int(self.size[lo:hi].max()), self.held + hi - lo
        return own

    def chain(self):
        """The likeliest walk: after each context, from the start on, the symbol with the shortest code, until one comes again."""
        if self.line is None:
            first = np.flatnonzero(np.r_[True, self.ctx[1:] != self.ctx[:-1]]) if len(self.ctx) else np.zeros(0, dtype=np.int64)
            order = np.lexsort((-self.value, self.size, self.ctx))  # in the order of ctx as it is, the shortest first; of equal length the heaviest has the greatest value, and an end that no walk has the least
            best = dict(zip(self.ctx[first].tolist(), order[first].tolist(), strict=True))
            at, rows, ctx = {}, [], markov.START
            while ctx in best and ctx not in at and self.sym[best[ctx]] != markov.ESC:
                at[ctx] = len(rows)
                rows.append(best[ctx])
                ctx = int(self.sym[best[ctx]])
            size = self.size[rows].astype(np.int64)
            left = np.repeat(np.cumsum(size), size) - np.arange(size.sum()) - 1
            bits = (np.repeat(self.value[rows], size) >> left & 1).astype(np.uint8)
            self.line = at, self.sym[rows].astype(np.int64), np.concatenate([[0], np.cumsum(size)]), bits
        return self.line

    def spans(self, data: bytes, n_bits: int, ctx: int = markov.START, most: int = MAX_SYMBOLS):
        """What :meth:`steps` decodes, as arrays of symbols and at last a status other than 'ok' as text."""
        syms = self.chain()[1]
        for x in self.stretches(data, n_bits, ctx, most):
            yield syms[x[0] : sum(x)] if isinstance(x, tuple) else x

    def stretches(self, data: bytes, n_bits: int, ctx: int = markov.START, most: int = MAX_SYMBOLS):
        """Spans of which those on the likeliest walk are no more than their place on it and their length.

        Bits that go on like the likeliest walk are compared with its bits at once; codes are free of prefixes, so equal bits are equal symbols.
        """
        places, syms, ends, line = self.chain()
        bits, at, made = np.unpackbits(np.frombuffer(data, dtype=np.uint8))[:n_bits], 0, 0
        while made < most:
            p = places.get(ctx)
            if p is not None:
                same, block, n = 0, 64, min(len(bits) - at, len(line) - int(ends[p]))
                while same < n:
                    hi = min(n, same + block)
                    off = np.flatnonzero(bits[at + same : at + hi] != line[ends[p] + same : ends[p] + hi])
                    if len(off):
                        same += int(off[0])
                        break
                    same, block = hi, 4 * block
                k = min(int(np.searchsorted(ends, ends[p] + same, "right")) - 1 - p, most - made)
                if k > 0:
                    yield p, k
                    made, at, ctx = made + k, at + int(ends[p + k] - ends[p]), int(syms[p + k - 1])
                    if ctx == markov.STOP:
                        return
                    continue
            own = self.of(ctx)
            if own is None:
                yield "invalid_prefix"
                return
            begin, code = at, ""
            while code not in own:
                if at - begin >= self.longest[ctx] or at >= len(bits):
                    yield "invalid_prefix" if at - begin >= self.longest[ctx] else "truncated"
                    return
                code += "1" if bits[at] else "0"
                at += 1
            sym = own[code]
            if sym == markov.ESC:
                if self.escape != "literal" or at + self.width > len(bits):
                    yield "escape_unsupported" if self.escape != "literal" else "truncated"
                    return
                sym = int("".join(map(str, bits[at : at + self.width].tolist())), 2)
                at += self.width
            yield np.array([sym], dtype=np.int64)
            made, ctx = made + 1, sym
            if sym == markov.STOP:
                return
        yield "runaway"

    def steps(self, data: bytes, n_bits: int, ctx: int = markov.START, most: int = MAX_SYMBOLS):
        """(ctx, code, symbol or status text, bit offset) of every step; a status other than 'ok' is the last step."""
        text = bin(int.from_bytes(b"\x01" + data, "big"))[3:][:n_bits] if data else ""
        at = 0
        for _ in range(most):
            own = self.of(ctx)
            if own is None:
                yield ctx, "", "invalid_prefix", at
                return
            begin = at
            while (code := text[begin:at]) not in own:
                if at - begin >= self.longest[ctx]:
                    yield ctx, code, "invalid_prefix", begin
                    return
                if at >= n_bits:
                    yield ctx, code, "truncated", begin
                    return
                at += 1
            sym = own[code]
            if sym == markov.ESC:
                if self.escape != "literal":
                    yield ctx, code, "escape_unsupported", begin
                    return
                if at + self.width > n_bits:
                    yield ctx, code, "truncated", begin
                    return
                sym = int(text[at : at + self.width], 2)
                at += self.width
            yield ctx, code, sym, begin
            if sym == markov.STOP:
                return
            ctx = sym
        yield ctx, "", "runaway", at


def _decoder(codebook: DataFrame, escape: str = "off", width: int = 0):
    """The codebook, of a checked size, as a broadcast decoder."""
    if codebook.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
        raise ValueError(f"codebook above {BROADCAST_ROWS} rows: decode blocks with decode_blocks_joined")
    value = F.when(F.col("code") == "", F.lit(0)).otherwise(F.conv("code", 2, 10).cast("long"))
    got = codebook.select("ctx", "sym", F.length("code").cast("byte").alias("size"), value.alias("value")).toArrow()
    columns = [c.to_numpy() for c in got.columns]
    order = np.argsort(columns[0], kind="stable")
    return codebook.sparkSession.sparkContext.broadcast(([c[order] for c in columns], escape, width))


def _run(encoded: DataFrame, codebook: DataFrame, schema: str, make, escape: str = "off", width: int = 0) -> DataFrame:
    sent = _decoder(codebook, escape, width)
    names = [f.strip().split(" ")[0] for f in schema.split(",")]
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}
    types = [kinds[f.strip().split(" ")[1]] for f in schema.split(",")]

    def run(batches):
        decoder = Decoder(*sent.value)
        for b in batches:
            out = []
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                for made in make(decoder, row):
                    out.append(made)
                    if len(out) >= 20_000:
                        yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names)
                        out = []
            if out:
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names)

    return encoded.mapInArrow(run, schema)


def _run_spans(encoded: DataFrame, codebook: DataFrame, make, escape: str = "off", width: int = 0) -> DataFrame:
    """(path_id, seq, node, status) of the streams (path_id, first seq, bits, n_bits, ctx, most, whether ``most`` is no error) that ``make`` gives for each row."""
    sent = _decoder(codebook, escape, width)

    def run(batches):
        decoder = Decoder(*sent.value)
        for b in batches:
            out, held = [], 0
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                path, seq, bits, n_bits, ctx, most, partial = make(row)
                for x in decoder.spans(bits or b"", n_bits or 0, ctx, most):
                    if isinstance(x, str):
                        if not (partial and x == "runaway"):
                            out.append((path, seq, None, x))
                            held += 1
                        break
                    n = len(x)
                    if x[n - 1] == markov.STOP:
                        x = x[: n - 1]
                    out += [(path, seq + i, x[i : i + 100_000], "ok") for i in range(0, len(x), 100_000)]
                    seq, held = seq + n, held + n
                    while held >= 100_000 or len(out) > 5_000:
                        yield _spanned(out)
                        out, held = [], 0
            if out:
                yield _spanned(out)

    return encoded.mapInArrow(run, "path_id long, seq long, node long, status string")


def _spanned(out: list[tuple]) -> pa.RecordBatch:
    size = np.array([1 if x is None else len(x) for _, _, x, _ in out])
    path, seq = (np.repeat(np.array([r[i] for r in out], dtype=np.int64), size) for i in (0, 1))
    seq += np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    node = np.concatenate([[0] if x is None else x for _, _, x, _ in out]).astype(np.int64)
    lost = np.repeat([x is None for _, _, x, _ in out], size)
    status = pa.array(np.repeat(np.array([s for *_, s in out], dtype=object), size), pa.string()) if lost.any() else pa.repeat(pa.scalar("ok"), len(node))
    return pa.record_batch([pa.array(path), pa.array(seq), pa.array(node, mask=lost), status], names=["path_id", "seq", "node", "status"])


def decode(encoded: DataFrame, codebook: DataFrame, first: int | None = None, escape: str = "off", width: int = 0) -> DataFrame:
    """(path_id, seq, node, status): the nodes of each walk, of its first symbols only if ``first`` is given; an error is a last row without node."""

    most = MAX_SYMBOLS if first is None else first
    return _run_spans(encoded.select("path_id", "bits", "n_bits"), codebook, lambda r: (r[0], 0, r[1], r[2], markov.START, most, first is not None), escape, width)


def decode_alike(encoded: DataFrame, codebook: DataFrame) -> DataFrame:
    """(path_id, seq, node, status) like :func:`decode`, for walks that go along the likeliest one for long stretches.

    A decoded stretch is a row until the nodes are listed: tile by tile of the likeliest walk, those of a group of walks that have the same
    stretch at the same place together, so that equal values follow one another (as :func:`runs.numbered` has them).
    """
    from . import runs

    spark, sent = encoded.sparkSession, _decoder(codebook)
    schema = "path_id long, place long, n long, seq long, node long, status string"

    def run(batches):
        decoder = Decoder(*sent.value)
        syms = decoder.chain()[1]
        for b in batches:
            out = []
            for path, bits, n_bits in zip(*(c.to_pylist() for c in b.columns), strict=True):
                seq = 0
                for x in decoder.stretches(bits or b"", n_bits or 0):
                    if isinstance(x, str):
                        out.append((path, None, None, seq, None, x))
                        break
                    place, n = x if isinstance(x, tuple) else (None, 1)
                    end = syms[place + n - 1] if place is not None else x[0]
                    if place is None and end != markov.STOP:
                        out.append((path, None, None, seq, int(end), "ok"))
                    elif place is not None and n > (end == markov.STOP):
                        out.append((path, place, n - int(end == markov.STOP), seq, None, "ok"))
                    seq += n
                if len(out) > 5_000:
                    yield _batch(out, schema)
                    out = []
            if out:
                yield _batch(out, schema)

    found = cut(encoded.select("path_id", "bits", "n_bits").mapInArrow(run, schema))
    line, size = Decoder(*sent.value).chain()[1], 1 << runs.TILE
    tiles = spark.createDataFrame([(i // size, line[i : i + size].tolist()) for i in range(0, len(line), size)], "_tile long, _nodes array<long>")
    tasks = runs._tasks(found)
    own = found.where("place is not null").withColumn("_group", F.pmod(F.xxhash64("path_id"), F.lit(runs.GROUPS * tasks))).repartition(tasks, "_group")
    last = F.col("place") + F.col("n") - 1
    each = own.withColumn("_tile", F.explode(F.sequence(F.shiftright("place", runs.TILE), F.shiftright(last, runs.TILE))))
    lo, hi = F.greatest("place", F.col("_tile") * size), F.least(last, (F.col("_tile") + 1) * size - 1)
    same = each.groupBy("_group", "_tile", (lo - F.col("_tile") * size).cast("int").alias("_lo"), (hi - lo + 1).cast("int").alias("_n"), (F.col("seq") - F.col("place") + lo).alias("_seq")).agg(F.collect_list("path_id").alias("_paths"))
    nodes = same.join(F.broadcast(tiles), "_tile").select("_paths", "_seq", F.posexplode(F.slice("_nodes", F.col("_lo") + 1, F.col("_n"))).alias("_i", "node"))
    listed = nodes.select("_paths", (F.col("_seq") + F.col("_i")).alias("seq"), "node").select(F.explode("_paths").alias("path_id"), "seq", "node", F.lit("ok").alias("status"))
    return listed.unionByName(found.where("place is null").select("path_id", "seq", "node", "status"))


def decode_blocks(blocks: DataFrame, codebook: DataFrame) -> DataFrame:
    """(path_id, seq, node, status) of blocks, each read alone from its entry context."""

    own = blocks.select("path_id", "entry_ctx", "first_seq", "n_symbols", "bits", "n_bits")
    return _run_spans(own, codebook, lambda r: (r[0], r[2], r[4], r[5], r[1], r[3], True))


def block_contexts(paths: DataFrame, block: int = 4096) -> DataFrame:
    """(path_id, block_no, ctx): the distinct contexts that a block goes through, to be stored beside its bits."""
    return markov.transitions(paths).select("path_id", F.floor(F.col("seq") / block).cast("long").alias("block_no"), "ctx").distinct()


def block_contexts_by_row(paths: DataFrame, codebook: DataFrame, block: int = 4096, spine: np.ndarray | None = None) -> DataFrame:
    """Contexts like those of :func:`block_contexts`, path by path."""

    def make(_, path, nodes):
        ctx = np.concatenate([[markov.START], nodes])
        own = np.unique(np.stack([np.arange(len(ctx)) // block, ctx], axis=1), axis=0)
        return [(path, number, x) for number, x in own.tolist()]

    return _by_row(paths, codebook, spine, "path_id long, block_no long, ctx long", make)


def decode_blocks_joined(blocks: DataFrame, contexts: DataFrame, codebook: DataFrame, symbols: int = 500_000) -> DataFrame:
    """(path_id, seq, node, status) like :func:`decode_blocks`, for codebooks of any size.

    Nothing is broadcast: shards of about ``symbols`` symbols, the blocks of some paths, meet the codes of their own contexts (``contexts`` of
    :func:`block_contexts`) in one task, which holds these codes only, once for all its blocks.
    """
    from . import shards

    blocks = cut(blocks.select("path_id", "block_no", "entry_ctx", "n_symbols", "n_bits", "first_seq", "bits"))
    n = blocks.agg(F.coalesce(F.sum("n_symbols"), F.lit(0))).first()[0]
    many = max(1, -(-n // symbols), min(blocks.sparkSession.sparkContext.defaultParallelism, n // 20_000))
    shard = F.pmod(F.xxhash64("path_id"), F.lit(many)).alias("shard")
    value = F.when(F.col("code") == "", F.lit(0)).otherwise(F.conv("code", 2, 10).cast("long"))
    codes = codebook.select("ctx", "sym", F.length("code").cast("long").alias("size"), value.alias("value"))
    none = F.lit(None)
    own = contexts.select(shard, "ctx").distinct().join(codes, "ctx")
    own = own.select("shard", F.lit(0).alias("kind"), "ctx", "sym", "size", "value", none.cast("long").alias("path_id"), none.cast("binary").alias("bits"))
    bits = blocks.select(shard, F.lit(1).alias("kind"), F.col("entry_ctx").alias("ctx"), F.col("n_symbols").alias("sym"), F.col("n_bits").alias("size"), F.col("first_seq").cast("long").alias("value"), "path_id", "bits")

    def run(batches):
        at, held, decoder = None, [], None
        for b in batches:
            key = 2 * b.column(0).to_numpy() + b.column(1).to_numpy()
            cuts = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if lo == hi:
                    continue
                if key[lo] >> 1 != at:
                    at, held, decoder = key[lo] >> 1, [], None
                part = b.slice(lo, hi - lo)
                ctx, sym, size, value = (part.column(i).to_numpy() for i in range(2, 6))
                if not key[lo] & 1:
                    held.append((ctx, sym, size, value))
                    continue
                if decoder is None:
                    none_ = np.zeros(0, dtype=np.int64)
                    decoder, held = shards.Together([np.concatenate([none_, *x]) for x in zip(*held, strict=True)] or [none_] * 4), []
                yield from shards.rows_of(decoder, part.column(6).to_numpy(), ctx, value, sym, size, part.column(7))

    met = own.unionByName(bits).repartition(many, "shard").sortWithinPartitions("shard", "kind")
    return met.mapInArrow(run, "path_id long, seq long, node long, status string")


def trace(encoded: DataFrame, codebook: DataFrame) -> DataFrame:
    """(path_id, step, ctx, code, sym, bit_offset, status) of every decoding step."""

    def make(decoder, row):
        path, bits, n_bits = row
        for step, (ctx, code, sym, at) in enumerate(decoder.steps(bits or b"", n_bits or 0)):
            yield path, step, ctx, code, None if isinstance(sym, str) else sym, at, sym if isinstance(sym, str) else "ok"

    return _run(encoded.select("path_id", "bits", "n_bits"), codebook, "path_id long, step long, ctx long, code string, sym long, bit_offset long, status string", make)


def verify(paths: DataFrame, encoded: DataFrame, codebook: DataFrame) -> DataFrame:
    """(path_id, seq, side) where decoding differs from the walk; must be empty."""
    want = paths.select("path_id", F.posexplode("nodes").alias("seq", "node")).withColumn("seq", F.col("seq").cast("long"))
    got = decode(encoded, codebook).select("path_id", "seq", F.col("node").alias("got"), "status")
    return want.join(got, ["path_id", "seq"], "full").where("not (node <=> got) or status <> 'ok'").select("path_id", "seq", F.when(F.col("got").isNull(), "lost").otherwise("changed").alias("side"))


def fit(paths: DataFrame, alpha: float = 1.0, force_stop: bool = True, escape: str = "off", cache: str = "profile", single_symbol: str = "empty") -> DataFrame:
    return fit_counts(markov.count(paths), alpha, force_stop, escape, cache, single_symbol)


def fit_counts(counts: DataFrame, alpha: float = 1.0, force_stop: bool = True, escape: str = "off", cache: str = "profile", single_symbol: str = "empty") -> DataFrame:
    """The codebook of transitions (ctx, sym, n) that are counted already."""
    return prefix.codebooks(markov.weights(counts, alpha, force_stop, escape), cache, single_symbol)


def refit(codebook: DataFrame, delta: DataFrame, alpha: float = 1.0, force_stop: bool = True, escape: str = "off", cache: str = "profile", single_symbol: str = "empty") -> DataFrame:
    """The codebook after the new counts ``delta``; only contexts that occur in them get new codes, all others keep theirs.

    The parameters must be those of :func:`fit`. A table of a context's new counts is as small as the delta, so the old book is read once and not ranked again.
    """
    touched = markov.touched(delta)
    counts = markov.update(codebook.join(touched, "ctx", "left_semi").where("n > 0"), delta)
    fresh = prefix.codebooks(markov.weights(counts, alpha, force_stop, escape), cache, single_symbol)
    return codebook.join(touched, "ctx", "left_anti").unionByName(fresh.select(*codebook.columns))


def save(path: str, encoded: DataFrame, codebook: DataFrame, index: DataFrame) -> None:
    """Parquet of the bits, the model as (ctx, sym, n, w, rank, len) and the label index; codes are made again on load."""
    encoded.write.mode("overwrite").parquet(f"{path}/bits")
    codebook.select("ctx", "sym", "n", "w", "rank", "len", "sig").sort("ctx", "len", "rank").write.mode("overwrite").parquet(f"{path}/model")
    index.write.mode("overwrite").parquet(f"{path}/index")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    return spark.read.parquet(f"{path}/bits"), prefix.canonical(spark.read.parquet(f"{path}/model")), spark.read.parquet(f"{path}/index")


def bytes_on_disk(spark: SparkSession, path: str) -> int:
    """Size of all files below a path, by the Hadoop file system that holds it."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return int(p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength())
