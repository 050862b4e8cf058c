"""Main text of web pages by a linear-chain conditional random field over leaf blocks.

A tolerant scanner turns a page into its leaf blocks: runs of text between block-level tags, each
with its chain of ancestor tags. Every block has features of its ancestors (tags,
hints in class and id), of its text and of its place; the field labels the blocks as
main or other together, trained on labelled pages and decoded by Viterbi. Scripts, styles, comments
and the head are never text.

The labelled pages of the registered query are made by :func:`labelled_pages`, from
templates with invented words; any iterable of (html, labels) will do.

Null html counts as empty; a page without main blocks gives an empty text; broken and
truncated markup is read as far as it goes; repeated rows are read each for themselves; a page of any length is read whole.
"""

from __future__ import annotations

import html
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Elements by what they do to text.
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr img".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea iframe svg object canvas math audio video select title".split())
#: Of these, the ones that go on to the end of the page if they are never closed; of others only the opening tag is left out then.
TO_THE_END = frozenset("script style textarea iframe title".split())
#: An opening tag of the first closes an open one of the second.
CLOSES = {
    **{t: ("p",) for t in "address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split()},
    "li": ("li", "p"), "dt": ("dt", "dd", "p"), "dd": ("dt", "dd", "p"), "tr": ("tr", "td", "th", "p"), "td": ("td", "th", "p"), "th": ("td", "th", "p"), "option": ("option",),
}
#: Where the search for an open tag to close ends.
SCOPES = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table")}
#: Parts of class and id names that hint at what a block is.
HINTS = (
    "ad", "ads", "advert", "advertisement", "alert", "article", "aside", "banner", "body", "breadcrumb", "breadcrumbs", "byline", "caption", "comment",
    "comments", "consent", "content", "cookie", "cookies", "copyright", "discussion", "disqus", "entry", "footer", "form", "gdpr", "header", "legal", "login",
    "main", "masthead", "menu", "modal", "nav", "navbar", "navigation", "newsletter", "notice", "outbrain", "pager", "pagination", "popup", "post", "promo", "related",
    "reply", "respond", "search", "share", "sharing", "sidebar", "signup", "site", "social", "sponsor", "sponsored", "story", "subscribe", "tags", "text", "toolbar", "widget",
)

_HINTS = frozenset(HINTS)
_PIECE = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*?)(/?)>|<[a-zA-Z/][^<>]*\Z|[^<]+|<", re.S)
_ATTR = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_NAME = re.compile(r"[a-z]+")
_SPACE = re.compile(r"\s+")


class Block:
    """Text, tag, open ancestors (tag, hints) from the root, and characters inside links."""

    __slots__ = ("linked", "path", "text")

    def __init__(self, text, path, linked):
        self.text, self.path, self.linked = text, path, linked


def leaf_blocks(page: str) -> list[Block]:
    """Leaf blocks of a page in order, character references decoded, white space turned into one space."""
    stack: list[tuple[str, tuple[str, ...]]] = []
    out: list[Block] = []
    parts: list[str] = []
    links = linked = 0
    skip = ""
    never_closed: set[str] = set()

    def flush():
        nonlocal linked
        if parts:
            text = _SPACE.sub(" ", html.unescape("".join(parts))).strip()
            if text:
                out.append(Block(text, tuple(stack), min(1.0, linked / len(text))))
            parts.clear()
        linked = 0

    def close(names, scope=()):
        for i in range(len(stack) - 1, -1, -1):
            if stack[i][0] in names:
                flush()
                del stack[i:]
                return
            if stack[i][0] in scope:
                return

    at, end = 0, len(page)
    while at < end:
        if skip:  # raw text ends with its own closing tag only
            m = re.compile(rf"</{skip}\b[^>]*(?:>|\Z)", re.I).search(page, at)
            if m:
                at = m.end()
            elif skip in TO_THE_END:
                at = end
            else:
                never_closed.add(skip)
            skip = ""
            continue
        m = _PIECE.match(page, at)
        at = m.end()
        tag = m[2]
        if tag is None:
            piece = m[0]
            if piece[0] != "<" or piece == "<":
                parts.append(piece)
                if links:
                    linked += len(piece)
            continue
        tag = tag.lower()
        if m[1]:
            if tag in INLINE:
                links -= tag == "a" and links > 0
            elif tag not in VOID:
                close((tag,), () if tag in ("body", "html") else ("article", "main", "body") if tag in ("p", "li") else ())
            continue
        if tag in RAW:
            if not m[4] and tag not in never_closed:
                skip = tag
            if tag != "wbr":
                parts.append(" ")
            continue
        if tag in INLINE:
            links += tag == "a"
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag in CLOSES:
            close(CLOSES[tag], SCOPES.get(tag, ("div", "article", "section", "main", "aside", "td", "li", "body", "blockquote", "table")))
        flush()
        if tag not in VOID and not m[4]:
            hints = set()
            for name, *values in _ATTR.findall(m[3]) if m[3] else ():
                hints.update(n for n in _NAME.findall("".join(values).lower()) if n in _HINTS)
            links = 0
            stack.append((tag, tuple(sorted(hints))))
    flush()
    return out


def features(blocks: list[Block]) -> list[list[str]]:
    """Names of the binary features of each block."""
    out = []
    for i, b in enumerate(blocks):
        own = {"bias"}
        for depth, (tag, hints) in enumerate(reversed(b.path)):
            if depth == 0:
                own.add(f"tag={tag}")
            own.add(f"under={tag}")
            for h in hints:
                own.add(f"hint={h}")
                if depth <= 1:
                    own.add(f"near={h}")
        inner = next((t for t, _ in reversed(b.path) if t in ("article", "main", "nav", "aside", "footer", "header", "form", "section", "ul", "table", "figure")), "none")
        own.add(f"inner={inner}")
        if not any(t in ("article", "main") for t, _ in b.path):
            own.add("outside")
        n = len(b.text)
        own.add(f"size={min(9, n.bit_length())}")
        own.add(f"linked={int(b.linked * 4)}")
        stops = len(re.findall(r"[.!?]", b.text))
        own.add(f"stops={min(3, stops)}")
        if "©" in b.text:
            own.add("copyright")
        own.add(f"place={min(3, 4 * i // len(blocks))}")
        out.append(sorted(own))
    return out


def _invented(rng: random.Random, words: int) -> str:
    made = ["".join(rng.choice("ban cor del fi gu hel im jo ka lor me nu op per qui ra so ti ul ve".split()) for _ in range(rng.randint(1, 4))) for _ in range(words)]
    for i in range(0, words, 9):
        made[min(words - 1, i + rng.randint(3, 8))] += "."
    return " ".join(made).capitalize()


def labelled_pages(n: int = 400, seed: int = 7) -> list[tuple[str, list[int]]]:
    """Pages of many templates, with the label of each leaf block: 1 for main text."""
    rng = random.Random(seed)
    pages = []
    for _ in range(n):
        out, labels = ["<html><head><title>x</title></head><body>"], []

        def block(markup, words, label, out=out, labels=labels):
            out.append(markup.format(_invented(rng, words)))
            labels.append(label)

        def menu(wrap, k, out=out, labels=labels):
            begin, end = wrap
            out.append(begin + "<ul>")
            for _ in range(k):
                block('<li><a href="/x">{}</a></li>', rng.randint(1, 3), 0)
            out.append("</ul>" + end)

        def boiler(out=out, labels=labels):
            kind = rng.choice(["ad", "cookie", "notice", "related", "share", "newsletter", "sidebar", "form", "aside", "promo", "comments"])
            if kind == "form":
                out.append('<form action="/s">')
                block("<p>{}</p>", rng.randint(1, 8), 0)
                out.append('<input name="q"><button>')
                block("{}", 1, 0)
                out.append("</button></form>")
            elif kind == "aside":
                out.append("<aside>")
                for _ in range(rng.randint(1, 3)):
                    block(rng.choice(["<p>{}</p>", "<h3>{}</h3>"]), rng.randint(2, 40), 0)
                out.append("</aside>")
            elif kind == "comments":
                out.append(f'<{(t := rng.choice(["div", "section"]))} {rng.choice(["class", "id"])}="{rng.choice(["comments", "comment-list", "discussion"])}">')
                block("<h3>{}</h3>", 1, 0)
                for _ in range(rng.randint(1, 5)):
                    out.append('<div class="comment">')
                    block("<p>{}</p>", rng.randint(4, 60), 0)
                    out.append("</div>")
                out.append(f"</{t}>")
            else:
                name = {"cookie": rng.choice(["cookie", "cookie-banner", "gdpr consent", "alert"]), "ad": rng.choice(["ad", "ads", "advert", "sponsored ad"]), "notice": rng.choice(["notice", "site-notice", "legal notice"]), "related": rng.choice(["related", "related post"]), "share": "social share", "newsletter": rng.choice(["newsletter signup", "subscribe"]), "sidebar": rng.choice(["sidebar", "widget"]), "promo": "promo banner"}[kind]
                out.append(f'<div {rng.choice(["class", "id"])}="{name}">')
                for _ in range(rng.randint(1, 2)):
                    block(rng.choice(["{}<br/>", "<p>{}</p>", "<p><a href='/y'>{}</a></p>"]).replace("<br/>", ""), rng.randint(2, 35), 0)
                    out.append("<div></div>")
                out.append("</div>")

        if rng.random() < 0.5:
            out.append("<header>")
            block(rng.choice(["<p>{}</p>", "<h1>{}</h1>", "<div class='site'>{}</div>"]), rng.randint(1, 6), 0)
            if rng.random() < 0.5:
                menu(("<nav>", "</nav>"), rng.randint(2, 7))
            out.append("</header>")
        if rng.random() < 0.8:
            menu(rng.choice([("<nav>", "</nav>"), ('<div class="menu">', "</div>"), ('<div id="navbar">', "</div>")]), rng.randint(2, 8))
        for _ in range(rng.randint(0, 2)):
            boiler()
        begin, end = rng.choice([("<article>", "</article>")] * 5 + [("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<div class="content">', "</div>"), ('<div id="main-content" class="post">', "</div>"), ('<div class="article-body">', "</div>"), ("<section><div class='entry text'>", "</div></section>")])
        out.append(begin)
        if rng.random() < 0.85:
            block(rng.choice(["<h1>{}</h1>", "<h2>{}</h2>", "<header><h1>{}</h1></header>" if "article" in begin else "<h1>{}</h1>"]), rng.randint(1, 12), 1)
        for _ in range(rng.randint(1, 10)):
            kind = rng.random()
            if kind < 0.72:
                block(rng.choice(["<p>{}</p>", "<p><b>{}</b></p>", "<p>{}", "<div>{}</div>", "<blockquote>{}</blockquote>"]), rng.choice([rng.randint(1, 6), rng.randint(5, 30), rng.randint(30, 90)]), 1)
            elif kind < 0.8:
                block(rng.choice(["<h2>{}</h2>", "<h3>{}</h3>"]), rng.randint(1, 7), 1)
            elif kind < 0.88:
                out.append("<ul>")
                for _ in range(rng.randint(1, 4)):
                    block(rng.choice(["<li>{}</li>", "<li><a href='/z'>{}</a></li>"]), rng.randint(2, 20), 1)
                out.append("</ul>")
            elif kind < 0.92:
                out.append("<table><tr>")
                for _ in range(3):
                    block("<td>{}</td>", rng.randint(1, 4), 1)
                out.append("</tr></table>")
            else:
                out.append("<div></div>")
                boiler()
        out.append(end)
        for _ in range(rng.randint(0, 3)):
            boiler()
        if rng.random() < 0.85:
            out.append(rng.choice(["<footer>", '<div class="footer">']))
            block(rng.choice(["<p>&copy; {}</p>", "&copy; {}", "<div>{}</div>"]), rng.randint(2, 20), 0)
            out.append("</footer></div>")
        out.append("</body></html>")
        page = "".join(out)
        if len(leaf_blocks(page)) == len(labels):
            pages.append((page, labels))
    return pages


class Field:
    """Weights of the features for main against other, of the transitions and of both ends."""

    def __init__(self, names: dict[str, int], weights: np.ndarray, moves: np.ndarray, start: np.ndarray, end: np.ndarray):
        self.names, self.weights, self.moves, self.start, self.end = names, weights, moves, start, end

    def emit(self, found: list[list[str]]) -> list[float]:
        w, names = self.weights, self.names
        return [float(sum(w[names[f]] for f in own if f in names)) for own in found]

    def decode(self, found: list[list[str]]) -> list[int]:
        """The most probable labels (Viterbi)."""
        if not found:
            return []
        m = self.moves.tolist()
        s0, s1 = float(self.start[0]), float(self.start[1])
        back = []
        for i, e in enumerate(self.emit(found)):
            if i:
                stay0, from1, from0, stay1 = s0 + m[0][0], s1 + m[1][0], s0 + m[0][1], s1 + m[1][1]
                back.append((int(from1 > stay0), int(stay1 > from0)))
                s0, s1 = max(stay0, from1), max(stay1, from0)
            s1 += e
        at = int(s1 + self.end[1] > s0 + self.end[0])
        labels = [at]
        for b in reversed(back):
            at = b[at]
            labels.append(at)
        return labels[::-1]


def loss(theta: np.ndarray, x: np.ndarray, on: np.ndarray, gold: np.ndarray) -> tuple[float, np.ndarray]:
    """Mean negative log-likelihood of sequences and its gradient, by the forward and backward sums.

    ``x`` (sequence, place, feature) is 0 or 1, ``on`` tells which places a sequence has, and ``gold`` holds the sums of
    features, transitions, first and last labels under the given labels, in the order of ``theta``.
    """
    n, longest, width = x.shape
    w, moves, start, end = np.split(theta, np.cumsum([width, 4, 2]))
    moves = moves.reshape(2, 2)
    last, every = on.sum(1) - 1, np.arange(n)
    score = np.zeros((n, longest, 2))
    score[:, :, 1] = x @ w.astype(np.float32)
    ahead, behind = np.zeros_like(score), np.zeros_like(score)
    ahead[:, 0] = score[:, 0] + start
    for j in range(1, longest):
        new = np.logaddexp(ahead[:, j - 1, :1] + moves[0], ahead[:, j - 1, 1:] + moves[1]) + score[:, j]
        ahead[:, j] = np.where(on[:, j, None], new, ahead[:, j - 1])
    behind[:] = end
    for j in range(longest - 2, -1, -1):
        nxt = score[:, j + 1] + behind[:, j + 1]
        new = np.stack([np.logaddexp(moves[a, 0] + nxt[:, 0], moves[a, 1] + nxt[:, 1]) for a in (0, 1)], 1)
        behind[:, j] = np.where(on[:, j + 1, None], new, end)
    total = np.logaddexp(ahead[every, last, 0] + end[0], ahead[every, last, 1] + end[1])
    prob = np.exp(ahead + behind - total[:, None, None]) * on[:, :, None]
    pair = np.exp(ahead[:, :-1, :, None] + moves + (score[:, 1:] + behind[:, 1:])[:, :, None, :] - total[:, None, None, None]) * on[:, 1:, None, None]
    expected = np.concatenate([np.einsum("ijf,ij->f", x, prob[:, :, 1]), pair.sum((0, 1)).ravel(), prob[:, 0].sum(0), prob[every, last].sum(0)])
    return float(total.sum() - gold @ theta) / n, (expected - gold) / n


def train(pages, steps: int = 250, rate: float = 0.1, ridge: float = 1e-3) -> Field:
    """A field fitted to (html, labels) by gradient steps on the conditional likelihood, all pages at once."""
    found = [(features(leaf_blocks(p)), y) for p, y in pages]
    names = {f: i for i, f in enumerate(sorted({f for own, _ in found for b in own for f in b}))}
    longest = max(len(y) for _, y in found)
    n = len(found)
    x = np.zeros((n, longest, len(names)), dtype=np.float32)
    y = np.zeros((n, longest), dtype=int)
    on = np.zeros((n, longest), dtype=bool)
    for i, (own, labels) in enumerate(found):
        for j, b in enumerate(own):
            x[i, j, [names[f] for f in b]] = 1
        y[i, : len(labels)], on[i, : len(labels)] = labels, True
    last = on.sum(1) - 1
    every = np.arange(n)
    sizes = [len(names), 4, 2, 2]
    theta, first, second = (np.zeros(sum(sizes)) for _ in range(3))
    gold = np.concatenate([
        np.einsum("ijf,ij->f", x, y * on),
        [((y[:, :-1] == a) & (y[:, 1:] == b) & on[:, 1:]).sum() for a in (0, 1) for b in (0, 1)],
        [(y[:, 0] == a).sum() for a in (0, 1)], [(y[every, last] == a).sum() for a in (0, 1)],
    ])
    for step in range(1, steps + 1):
        slope = loss(theta, x, on, gold)[1] + ridge * theta
        first, second = 0.9 * first + 0.1 * slope, 0.999 * second + 0.001 * slope**2
        theta -= rate * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.999**step)) + 1e-8)
    w, moves, start, end = np.split(theta, np.cumsum(sizes)[:-1])
    return Field(names, w, moves.reshape(2, 2), start, end)


@lru_cache(maxsize=1)
def default_field() -> Field:
    return train(labelled_pages())


def main_text(page: str, field: Field) -> str:
    blocks = leaf_blocks(page)
    return " ".join(b.text for b, label in zip(blocks, field.decode(features(blocks)), strict=True) if label)


def extract(pages: DataFrame, field: Field | None = None, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """(the kept columns, text, n_chars) of every page."""
    sent = pages.sparkSession.sparkContext.broadcast(field or default_field())

    def run(batches):
        for b in batches:
            texts = [main_text(p or "", sent.value) for p in b.column(b.num_columns - 1).to_pylist()]
            yield pa.record_batch([*(b.column(i) for i in range(len(keep))), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=[*keep, "text", "n_chars"])

    rows = pages.select(*keep, F.col(html_col).cast("string").alias("html_"))
    kinds = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in keep)
    return rows.mapInArrow(run, f"{kinds}, text string, n_chars long")
