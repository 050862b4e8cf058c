"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

The vocabulary is a file of ranks. The library works on characters, so bytes pass
through the usual byte-to-character table of byte-level models, and every pair of
tokens that makes a token becomes a merge with that token's rank: the same merges
that a rank-driven encoder finds. Matches that are tokens themselves are taken whole
before any merge.

The file is read on the driver and its contents are broadcast; executors need no
file. Null counts as empty, an empty text has no tokens, a text of any length is one
unit, and repeated rows are encoded each for themselves.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.memory import trimmed
from .common import text_of

#: Characters of text that are encoded at once; a longer text makes a batch of its own.
CHUNK_CHARS = 1 << 18
#: Words that a process remembers.
CACHED_WORDS = 1 << 17
#: Where a text may be parted without changing any match.
PARTING = re.compile(r" (?=\S)")


def byte_characters() -> list[str]:
    """The character that stands for each byte: printable Latin-1 for itself, the rest from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}


def tokenizer_json(ranks: dict[bytes, int], pattern: str) -> str:
    """The library's own description of the model with these ranks."""
    chars = byte_characters()
    name = {t: "".join(chars[b] for b in t) for t in ranks}
    merges = []
    for token in sorted(ranks, key=ranks.get):
        for cut_at in range(len(token) - 1, 0, -1):
            left, right = token[:cut_at], token[cut_at:]
            if left in ranks and right in ranks:
                merges.append([name[left], name[right]])
    return json.dumps(
        {
            "version": "1.0", "truncation": None, "padding": None, "added_tokens": [], "normalizer": None,
            "pre_tokenizer": {
                "type": "Sequence",
                "pretokenizers": [
                    {"type": "Split", "pattern": {"Regex": pattern}, "behavior": "Isolated", "invert": False},
                    {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": False, "use_regex": False},
                ],
            },
            "post_processor": None, "decoder": {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": False, "use_regex": False},
            "model": {
                "type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": None,
                "fuse_unk": False, "byte_fallback": False, "ignore_merges": True,
                "vocab": {name[t]: r for t, r in ranks.items()}, "merges": merges,
            },
        }
    )


class Codec:
    """Encoder and decoder of one process."""

    def __init__(self, description: str):
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_str(description)
        self.words: dict[str, bytes] = {}
        back = {c: b for b, c in enumerate(byte_characters())}
        vocab = self.model.get_vocab(with_added_tokens=False)
        self.bytes_of = [b""] * (max(vocab.values(), default=-1) + 1)
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(back[c] for c in token)
        self.space_led = np.array([b[:1] == b" " for b in self.bytes_of], dtype=bool)

    def whole(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers, straight from the library."""
        return [np.asarray(e.ids, dtype="<u4").tobytes() for e in self.model.encode_batch_fast(texts, add_special_tokens=False)]

    def packed(self, texts: list[str]) -> list[bytes]:
        """Like :meth:`whole`, but each different space-led word is encoded once and remembered.

        No match of the pattern crosses a space that a character other than white
        space follows, and what stands before such a space is matched alike whether
        the text goes on or ends. So a text falls apart there and nowhere else.
        """
        parts = [t.split(" ") for t in texts]
        new = self._unknown(parts)
        odd = {w for w in new if not w or w[0].isspace()}
        if odd:
            parts = [p if odd.isdisjoint(p[1:]) else PARTING.split(t) for p, t in zip(parts, texts, strict=True)]
            new = self._unknown(parts)
        if len(self.words) + len(new) > CACHED_WORDS:
            self.words.clear()
            new = self._unknown(parts)
        self.words.update(self._led(new))
        look = self.words.__getitem__
        heads = self.whole([p[0] for p in parts])
        out = [b"".join([head, *map(look, p[1:])]) for head, p in zip(heads, parts, strict=True)]
        if len(self.words) > CACHED_WORDS:
            self.words.clear()
        return out

    def _unknown(self, parts: list[list[str]]) -> set[str]:
        known = self.words
        return {w for w in set().union(*[p[1:] for p in parts]) if w not in known}

    def _led(self, words: set[str]) -> dict[str, bytes]:
        """Ids of each word after one space; all words without a space of their own go as one text."""
        plain = sorted(w for w in words if " " not in w)
        spaced = sorted(w for w in words if " " in w)
        out = dict(zip(spaced, self.whole([" " + w for w in spaced]), strict=True))
        if plain:
            ids = np.asarray(self.model.encode_batch_fast([" " + " ".join(plain)], add_special_tokens=False)[0].ids, "<u4")
            starts = np.flatnonzero(self.space_led[ids])
            data, at = ids.tobytes(), (np.append(starts, len(ids)) * 4).tolist()
            out.update((w, data[a:b]) for w, a, b in zip(plain, at[:-1], at[1:], strict=True))
        return out

    def encode(self, texts: list[str]) -> list[list[int]]:
        return [np.frombuffer(b, "<u4").tolist() for b in self.packed(texts)]

    def offsets(self, text: str) -> list[tuple[int, int]]:
        """Byte range of each token in the UTF-8 text; tokens that split a character have their own bytes."""
        ends = np.cumsum([0, *(len(self.bytes_of[i]) for i in self.encode([text])[0])])
        return [(int(a), int(b)) for a, b in zip(ends[:-1], ends[1:], strict=True)]

    def decode_bytes(self, ids) -> bytes:
        table = self.bytes_of
        return b"".join([table[i] for i in ids])

    def decode(self, ids) -> str:
        """Text of the ids; bytes that end within a character become U+FFFD."""
        return self.decode_bytes(ids).decode("utf-8", "replace")


_codecs: dict[str, Codec] = {}


def codec(description: str) -> Codec:
    key = hashlib.sha256(description.encode()).hexdigest()
    if key not in _codecs:
        _codecs[key] = Codec(description)
    return _codecs[key]


def chunks(texts: list[str], most: int = CHUNK_CHARS) -> Iterator[tuple[int, list[str]]]:
    """(place of the first, texts) in runs of about ``most`` characters."""
    at, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield at, texts[at:i]
            at, size = i, 0
        size += len(t)
    if at < len(texts):
        yield at, texts[at:]


def _prepared(docs: DataFrame, vocabulary: str, pattern: str):
    return docs.sparkSession.sparkContext.broadcast(tokenizer_json(read_ranks(vocabulary), pattern))


def encode(docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<int>) of every row."""
    description = _prepared(docs, vocabulary, pattern)

    def run(batches):
        own = codec(description.value)
        for batch in batches:
            for at, texts in chunks(batch.column(1).to_pylist()):
                ids = own.encode(texts)
                yield pa.record_batch([batch.column(0).slice(at, len(texts)), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    rows = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text"))
    return rows.mapInArrow(trimmed(run), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, ids array<int>")


def decode(encoded: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, bytes, text) of every row of ids."""
    description = _prepared(encoded, vocabulary, pattern)

    def run(batches):
        own = codec(description.value)
        for batch in batches:
            data = [own.decode_bytes(ids or []) for ids in batch.column(1).to_pylist()]
            text = [d.decode("utf-8", "replace") for d in data]
            yield pa.record_batch([batch.column(0), pa.array(data, pa.binary()), pa.array(text, pa.string())], names=["doc_id", "bytes", "text"])

    rows = encoded.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids"))
    return rows.mapInArrow(trimmed(run), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, bytes binary, text string")


def round_trip(docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): digests of the ids and of what they decode to."""
    description = _prepared(docs, vocabulary, pattern)

    def run(batches):
        own = codec(description.value)
        for batch in batches:
            counts, of_ids, of_text = [], [], []
            for _, texts in chunks(batch.column(1).to_pylist()):
                for packed in own.packed(texts):
                    counts.append(len(packed) // 4)
                    of_ids.append(hashlib.sha256(packed).hexdigest())
                    of_text.append(hashlib.sha256(own.decode_bytes(np.frombuffer(packed, "<u4").tolist())).hexdigest())
            yield pa.record_batch(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    rows = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(trimmed(run), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
