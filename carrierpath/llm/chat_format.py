"""Chat formatting in budgeted windows.

A conversation becomes one or more training windows. Prefix sums of the tokens of its
turns choose spans that begin and end with turns and stay within ``budget``; every
window repeats the leading system turn and at most ``history`` turns before its span. Only
assistant texts of the span itself are under the loss mask, so each is trained on once however
often it is repeated as history. A turn above the budget makes a window of its own and
stays whole.

Template: ``<<SYS>>text<</SYS>>``, ``[INST]text[/INST]``, ``<s>text</s>`` for system, user and
assistant, ``[TURN]role[AS]text[/TURN]`` for any other role, ``[TURN][AS]`` with no role name
for null. Control strings inside a text, and the escape sign itself, are escaped reversibly,
so the output can be read back to the same turns.

The rows of a conversation are sorted and streamed through one task, which holds one
window and its history, not the conversation. Null texts are empty, null turns come
first, rows that tie on the turn are ordered by role and text, repeated rows are turns
of their own, the null conversation id is a conversation, and an empty table gives no windows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from itertools import groupby
from operator import itemgetter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Tokens of a window and turns of repeated history.
BUDGET, HISTORY = 1024, 2

# Opening and closing marks by role.
MARKS = {"system": ("<<SYS>>", "<</SYS>>"), "user": ("[INST]", "[/INST]"), "assistant": ("<s>", "</s>")}
OTHER, NAMED, OTHER_END, NO_ROLE = "[TURN]", "[AS]", "[/TURN]", "\\0"

_CONTROL = re.compile("|".join(map(re.escape, ["\\", *(m for pair in MARKS.values() for m in pair), OTHER, NAMED, OTHER_END])))
_OPEN = re.compile("|".join(map(re.escape, [*(a for a, _ in MARKS.values()), OTHER])))
_TOKEN = re.compile(r"\w+|[^\w\s]")


def escape(text: str) -> str:
    r"""``\`` is doubled; a control string gets one after its first character."""
    return _CONTROL.sub(lambda m: "\\\\" if m[0] == "\\" else m[0][0] + "\\" + m[0][1:], text)


def unescape(text: str) -> str:
    return re.sub(r"\\(\\?)", r"\1", text)


def n_tokens(text: str) -> int:
    """Words and punctuation marks, a stand-in for a tokenizer's count."""
    return sum(1 for _ in _TOKEN.finditer(text))


def render(role: str | None, text: str) -> tuple[str, int, int]:
    """The marked turn, and where its text begins and ends in it."""
    if role in MARKS:
        begin, end = MARKS[role]
    else:
        begin, end = OTHER + (NO_ROLE if role is None else escape(role)) + NAMED, OTHER_END
    body = escape(text)
    return begin + body + end, len(begin), len(begin) + len(body)


def parse(window: str) -> Iterator[tuple[str | None, str, int, int]]:
    """(role, text, begin, end) of each turn of a window; the inverse of :func:`render`."""
    at = 0
    role_of = {a: (r, b) for r, (a, b) in MARKS.items()}
    while at < len(window):
        mark = _OPEN.match(window, at)
        if not mark:
            raise ValueError(f"no turn at {at}")
        at = mark.end()
        if mark[0] in role_of:
            role, close = role_of[mark[0]]
        else:
            name_end = window.index(NAMED, at)
            name = window[at:name_end]
            role, close, at = None if name == NO_ROLE else unescape(name), OTHER_END, name_end + len(NAMED)
        end = window.index(close, at)
        yield role, unescape(window[at:end]), at, end
        at = end + len(close)


def windows(turns: Iterator[tuple[str | None, str]], budget: int, history: int) -> Iterator[dict]:
    """Windows of the turns of one conversation, in order."""
    system: list[tuple[str | None, str]] = []
    past: list[tuple[tuple[str | None, str], int]] = []
    span: list[tuple[tuple[str | None, str], int]] = []
    fixed = spent = no = 0

    def close():
        nonlocal no
        repeated = past[-history:] if history else []
        room = budget - fixed - spent
        while repeated and sum(n for _, n in repeated) > room:  # history never pushes the span out
            repeated = repeated[1:]
        out, loss, length = [], [], 0
        for i, turn in enumerate([*system, *(t for t, _ in repeated), *(t for t, _ in span)]):
            piece, begin, end = render(*turn)
            if turn[0] == "assistant" and i >= len(system) + len(repeated):
                loss.append((length + begin, length + end))
            out.append(piece)
            length += len(piece)
        made = {"window": no, "formatted": "".join(out), "loss": loss, "n_system": len(system), "n_history": len(repeated), "n_new": len(span), "n_tokens": fixed + spent + sum(n for _, n in repeated)}
        past.extend(span)
        del past[: max(0, len(past) - history)]
        span.clear()
        no += 1
        return made

    first = True
    for turn in turns:
        cost = n_tokens(turn[1])
        if first and turn[0] == "system":
            system.append(turn)
            fixed += cost
        else:
            if span and fixed + spent + cost > budget:
                yield close()
                spent = 0
            span.append((turn, cost))
            spent += cost
        first = False
    if span or system and not no:
        yield close()


def _conversations(batches) -> Iterator[tuple[object, Iterator[tuple[str | None, str]]]]:
    rows = ((c, r, t) for b in batches for c, r, t in zip(*(b.column(i).to_pylist() for i in (0, 2, 3)), strict=True))
    for conv, own in groupby(rows, itemgetter(0)):
        yield conv, ((role, text or "") for _, role, text in own)


_WINDOW = "window long, formatted string, loss array<struct<begin:int,end:int>>, n_system int, n_history int, n_new int, n_tokens long"
_SPAN = pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32())]))


def format_chats(conversations: DataFrame, budget: int = BUDGET, history: int = HISTORY, batch_chars: int = 1 << 20) -> DataFrame:
    """One row per window: conv_id, window, formatted, loss spans, counts of turns and tokens.

    Rows come sorted by conversation and window within a partition, and no
    conversation is spread over partitions.
    """

    def run(batches):
        names = ["conv_id", "window", "formatted", "loss", "n_system", "n_history", "n_new", "n_tokens"]
        kinds = [pa.int64(), pa.int64(), pa.string(), _SPAN, pa.int32(), pa.int32(), pa.int32(), pa.int64()]
        held, size = [], 0
        for conv, turns in _conversations(batches):
            for w in windows(turns, budget, history):
                w["loss"] = [{"begin": a, "end": b} for a, b in w["loss"]]
                held.append([conv, *(w[n] for n in names[1:])])
                size += len(w["formatted"])
                if size > batch_chars:
                    yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names=names)
                    held, size = [], 0
        if held:
            yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names=names)

    turns = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").alias("turn"), F.col("role").alias("role"), F.col("text").alias("text"))
    return turns.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").mapInArrow(run, f"conv_id long, {_WINDOW}")


def read_back(formatted: DataFrame) -> DataFrame:
    """What the windows of :func:`format_chats` say, by conversation.

    (conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, n_windows). Takes the windows as they
    come, so it must follow :func:`format_chats` directly.
    """

    def run(batches):
        cols = ("conv_id", "formatted", "loss", "n_system", "n_history")
        rows = (r for b in batches for r in zip(*(b.column(c).to_pylist() for c in cols), strict=True))
        out = []
        for conv, own in groupby(rows, itemgetter(0)):
            turns, loss, n, loss_chars, chars, n_windows = hashlib.sha256(), hashlib.sha256(), 0, 0, 0, 0
            for _, text, spans, n_system, n_history in own:
                for i, (role, said, _, _) in enumerate(parse(text)):
                    if n_system <= i < n_system + n_history or i < n_system and n_windows:
                        continue
                    turns.update(f"{'' if role is None else role}\n{said}\n".encode("utf-8", "surrogatepass"))
                    n += 1
                for s in spans:
                    said = unescape(text[s["begin"] : s["end"]])
                    loss.update(said.encode("utf-8", "surrogatepass"))
                    loss_chars += len(said)
                chars += len(text)
                n_windows += 1
            out.append((conv, n, turns.hexdigest(), loss_chars, loss.hexdigest(), chars, n_windows))
            if len(out) >= 4096:
                yield batch(out)
                out = []
        if out:
            yield batch(out)

    def batch(out):
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64())
        return pa.record_batch([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_windows"])

    return formatted.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_windows long")
