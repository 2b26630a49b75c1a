"""HTML extraction: a linear-chain conditional random field labels the leaf blocks of the DOM as main text or not, from their ancestors and their text,
and is decoded by Viterbi. It is trained here, by likelihood, on labelled pages that a generator makes from layouts in common use.
"""

from __future__ import annotations

import html as html_lib
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick

#: Elements by their role in parsing.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
UNSEEN = frozenset("script style noscript template head title svg canvas iframe object select textarea button option datalist".split())
#: Elements that may stand in a head; any other start tag ends it.
IN_HEAD = frozenset("html head base basefont bgsound link meta noframes noscript script style template title".split())
RAW = frozenset("script style textarea title noscript iframe template".split())
BLOCK = frozenset(
    "address article aside blockquote body br center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre "
    "section summary table tbody td tfoot th thead tr ul".split()
)
#: Start tags that end an open element of their own name.
ENDS_OWN = frozenset(("button", "select", "option"))
CLOSES_P = BLOCK - {"br", "body", "html", "dd", "dt", "li", "td", "th", "tr", "tbody", "thead", "tfoot"}
#: Ancestors and words of class and id attributes that are features.
TAGS = ("nav", "header", "footer", "aside", "form", "article", "main", "section", "ul", "ol", "li", "table", "h1", "h2", "h3", "p", "a", "blockquote", "pre", "figcaption", "dialog", "menu", "label")
HINTS = {
    "menu": "menu nav navbar navigation breadcrumb breadcrumbs pager pagination toc tabs skip",
    "top": "header masthead topbar top logo branding",
    "bottom": "footer foot copyright colophon legal bottom",
    "side": "sidebar side aside rail widget related recommended recommendations popular trending more tags",
    "notice": "cookie cookies consent notice gdpr banner popup modal newsletter subscribe signup alert paywall",
    "advert": "ad ads advert adverts advertisement sponsor sponsored promo promotion adsense dfp",
    "reader": "comment comments reply replies disqus respond discussion reader readers thread",
    "share": "share sharing social follow",
    "meta": "byline author date meta timestamp",
    "body": "content article post entry story text body main prose hentry articlebody",
}
#: Hints that an element's other names can outweigh.
MILD = frozenset(("side", "meta", "share", "top", "bottom"))
_HINT_OF = {w: k for k, words in HINTS.items() for w in words.split()}

# quotes enclose a value only where they follow the equals sign
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>=]|=\s*(?:\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z)|[^\s>]*))*+)>?", re.S)
_ATTR = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"[a-z]+")


class Leaf:
    """One leaf block: its text, the ancestors that are features, and the share of its text in links."""

    __slots__ = ("text", "names", "linked")

    def __init__(self, text: str, names: frozenset[str], linked: float):
        self.text, self.names, self.linked = text, names, linked


@lru_cache(50_000)
def _marks(name: str, attrs: str) -> frozenset[str]:
    """Features that an open element gives to all blocks in it. Names that hint at both the text and what surrounds it, as story-date-tags, are one mixed hint."""
    out, hints = {f"<{name}>"} if name in TAGS else set(), set()
    for m in _ATTR.finditer(attrs):
        for w in _WORD.findall((m[2] or m[3] or m[4] or "").lower()):
            if w in _HINT_OF and name not in ("body", "html"):
                hints.add(_HINT_OF[w])
            if m[1].lower() == "role" and w in ("navigation", "banner", "contentinfo", "complementary", "search"):
                out.add("." + {"navigation": "menu", "banner": "top", "contentinfo": "bottom", "complementary": "side", "search": "menu"}[w])
    if "body" in hints and hints & MILD and not hints - MILD - {"body"}:
        hints = {"mixed"}
    return frozenset(out | {f".{x}" for x in hints})


def leaf_blocks(page: str) -> list[Leaf]:
    """The leaf blocks of a whole page in page order: text between the borders of block elements, character references decoded, white space runs as one
    space. Unclosed and misnested elements are closed where HTML's rules for head, p, li, button, select, option and table cells, or the end of an outer
    element, close them. Elements that hide their text but lack an end tag, such as a button, hide it up to the next block only."""
    out: list[Leaf] = []
    # each open element with what holds below it: features, whether text is hidden, whether it is in a link
    stack: list[tuple[str, frozenset[str], bool, bool]] = []
    places: dict[str, list[int]] = {}  # of open elements, by name
    blocks: list[int] = []  # places of open block elements
    loose: list[int] = []  # places of elements that hide their text up to the next block only
    parts: list[str] = []
    linked = [0]

    def cut() -> None:
        if parts:
            text = " ".join("".join(parts).split())
            if text:
                out.append(Leaf(text, stack[-1][1] if stack else frozenset(), min(1.0, linked[0] / len(text))))
            parts.clear()
            linked[0] = 0

    def push(name: str, attrs: str, hides: bool, until_block: bool = False) -> None:
        _, names, hidden, link = stack[-1] if stack else ("", frozenset(), False, False)
        marks, k = _marks(name, attrs), len(stack)
        stack.append((name, names if marks <= names else names | marks, hidden or hides, link or name == "a"))
        places.setdefault(name, []).append(k)
        if name in BLOCK:
            blocks.append(k)
        if until_block:
            loose.append(k)

    def drop(k: int) -> None:
        """Closes the elements from place k on."""
        while len(stack) > k:
            places[stack.pop()[0]].pop()
        while blocks and blocks[-1] >= k:
            blocks.pop()
        while loose and loose[-1] >= k:
            loose.pop()

    def last(*names: str) -> int:
        """Place of the innermost open element with one of the names."""
        return max((places[x][-1] for x in names if places.get(x)), default=-1)

    def say(raw: str) -> None:
        if stack and stack[-1][0] == "head" and raw.strip():
            drop(len(stack) - 1)
        if raw and not (stack and stack[-1][2]):
            text = html_lib.unescape(raw) if "&" in raw else raw
            parts.append(text)
            if stack and stack[-1][3]:
                linked[0] += len(text.strip())

    def close(k: int) -> None:
        if blocks and blocks[-1] >= k:
            drop(blocks[-1] + 1)
            cut()
        drop(k)

    at, n = 0, len(page)
    while at < n:
        begin = page.find("<", at)
        if begin < 0:
            say(page[at:])
            break
        m = _TOKEN.match(page, begin)
        if m is None:
            say(page[at : begin + 1])
            at = begin + 1
            continue
        say(page[at:begin])
        at = m.end()
        if m[2] is None:
            continue
        name = m[2].lower()
        if m[1]:
            if places.get(name):
                if name in BLOCK:
                    cut()
                close(last(name))
            elif name == "p":
                cut()
            continue
        if name not in IN_HEAD and places.get("head"):
            drop(places["head"][0])
        if name in BLOCK and name not in ("br", "hr") and loose:
            drop(loose[0])
        if name in ENDS_OWN and last(name) > last("table", "td", "th", "object"):
            drop(last(name))
        if name in BLOCK:
            cut()
            if name in CLOSES_P:
                if blocks and stack[blocks[-1]][0] == "p":
                    drop(blocks[-1])
            elif name in ("li", "td", "th", "tr", "dd", "dt"):
                k = last(*{"tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "dd": ("dd", "dt"), "dt": ("dd", "dt")}.get(name, (name,)))
                if k > last("ul", "ol", "table", "dl", "menu"):
                    drop(last("tr") if name == "tr" and last("tr") > last("table") else k)
        if name in VOID:
            continue
        if name in RAW and not (m[3] or "").rstrip().endswith("/"):
            end = _end_of(name).search(page, at)
            at = end.end() if end else n
            continue
        if (m[3] or "").rstrip().endswith("/") and name not in BLOCK:
            continue
        if name in UNSEEN and name != "head":
            after = _tag_of(name).search(page, at)
            push(name, m[3] or "", True, after is None or not after[1])
        else:
            push(name, m[3] or "", name in UNSEEN)
    cut()
    return out


@lru_cache(100)
def _end_of(name: str) -> re.Pattern:
    return re.compile(rf"</{name}\s*>?", re.I)


@lru_cache(100)
def _tag_of(name: str) -> re.Pattern:
    return re.compile(rf"<(/?){re.escape(name)}(?![^\s/>])", re.I)


def features(leaves: list[Leaf]) -> list[tuple[str, ...]]:
    """Names of the features that hold of each block."""
    rows = []
    for i, x in enumerate(leaves):
        t, n = x.text, len(x.text.split())
        f = [*x.names, "len0" if n < 3 else "len1" if n < 8 else "len2" if n < 20 else "len3"]
        if not x.names:
            f.append("bare")
        if x.linked > 0.6:
            f.append("linked")
        elif x.linked > 0.2:
            f.append("links")
        if t[-1] in ".!?…:;\"”":
            f.append("stop")
        if "©" in t or "&copy" in t:
            f.append("©")
        if i < 2:
            f.append("first")
        if i >= len(leaves) - 2:
            f.append("last")
        rows.append(tuple(f))
    return rows


class ChainModel:
    """Linear-chain conditional random field with two labels (1: main text)."""

    def __init__(self, names: list[str], emit: np.ndarray, move: np.ndarray):
        self.emit = {n: float(emit[i, 1] - emit[i, 0]) for i, n in enumerate(names)}
        self.bias = self.emit.pop("")
        self.move = move.tolist()

    def decode(self, rows: list[tuple[str, ...]]) -> list[int]:
        """Viterbi."""
        if not rows:
            return []
        m, get, back = self.move, self.emit.get, []
        a, b = 0.0, self.bias + sum(get(f, 0.0) for f in rows[0])
        for r in rows[1:]:
            e = self.bias + sum(get(f, 0.0) for f in r)
            a0, b0, a1, b1 = a + m[0][0], b + m[1][0], a + m[0][1], b + m[1][1]
            back.append((b0 > a0, b1 > a1))
            a, b = max(a0, b0), max(a1, b1) + e
        now = int(b > a)
        out = [now]
        for x in reversed(back):
            now = int(x[now])
            out.append(now)
        return out[::-1]


def train_chain(pages: list[tuple[list[tuple[str, ...]], list[int]]], steps: int = 300, rate: float = 0.1, decay: float = 1e-3) -> ChainModel:
    """Maximises the conditional likelihood of labelled block sequences (forward-backward, Adam), all sequences together, padded."""
    pages = [p for p in pages if p[0]]
    names = ["", *sorted({f for rows, _ in pages for r in rows for f in r})]
    at = {n: i for i, n in enumerate(names)}
    b, t = len(pages), max(len(r) for r, _ in pages)
    x, y, live = np.zeros((b, t, len(names))), np.zeros((b, t), int), np.zeros((b, t), bool)
    for i, (rows, labels) in enumerate(pages):
        live[i, : len(rows)] = True
        y[i, : len(rows)] = labels
        for j, r in enumerate(rows):
            x[i, j, [0, *(at[f] for f in r)]] = 1
    emit, move = np.zeros((len(names), 2)), np.zeros((2, 2))
    truth_emit = np.einsum("btf,btk->fk", x, np.eye(2)[y] * live[..., None])
    pair = live[:, 1:]
    truth_move = np.array([[((y[:, :-1] == p) & (y[:, 1:] == q) & pair).sum() for q in (0, 1)] for p in (0, 1)], float)
    state = [np.zeros_like(v) for v in (emit, move, emit, move)]
    for step in range(1, steps + 1):
        score = x @ emit
        fwd, bwd = np.zeros((b, t, 2)), np.zeros((b, t, 2))
        fwd[:, 0] = score[:, 0]
        for k in range(1, t):
            new = np.logaddexp(fwd[:, k - 1, :1] + move[0], fwd[:, k - 1, 1:] + move[1]) + score[:, k]
            fwd[:, k] = np.where(live[:, k, None], new, fwd[:, k - 1])
        for k in range(t - 2, -1, -1):
            into = (score[:, k + 1] + bwd[:, k + 1])[:, None, :] + move[None]
            bwd[:, k] = np.where(live[:, k + 1, None], np.logaddexp(into[..., 0], into[..., 1]), 0.0)
        z = np.logaddexp(fwd[:, -1, 0], fwd[:, -1, 1])
        single = np.exp(fwd + bwd - z[:, None, None]) * live[..., None]
        double = np.exp(fwd[:, :-1, :, None] + move + (score[:, 1:] + bwd[:, 1:])[:, :, None, :] - z[:, None, None, None]) * pair[..., None, None]
        grads = [(truth_emit - np.einsum("btf,btk->fk", x, single)) / b - decay * emit, (truth_move - double.sum((0, 1))) / b - decay * move]
        for k, (v, g) in enumerate(zip((emit, move), grads, strict=True)):
            state[k] = 0.9 * state[k] + 0.1 * g
            state[k + 2] = 0.99 * state[k + 2] + 0.01 * g * g
            v += rate * (state[k] / (1 - 0.9**step)) / (np.sqrt(state[k + 2] / (1 - 0.99**step)) + 1e-8)
    return ChainModel(names, emit, move)


def labelled_pages(n: int = 240, seed: int = 5) -> list[tuple[str, list[str]]]:
    """(html, texts of its main blocks): pages in layouts in common use, with made-up words, some unclosed or cut off."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice(("ka", "lo", "mi", "ren", "tu", "vas", "el", "or", "an", "si")) for _ in range(rng.randint(1, 4)))
    some = lambda lo, hi: " ".join(word() for _ in range(rng.randint(lo, hi)))
    sentence = lambda lo, hi: some(lo, hi).capitalize() + rng.choice((".", ".", ".", "!", "?", ""))
    links = lambda k: "".join(f'<li><a href="/{word()}">{some(1, 2)}</a></li>' for _ in range(k))
    made = []
    for _ in range(n):
        main: list[str] = []

        def para(tag: str = "p", lo: int = 1, hi: int = 60, main: list[str] = main) -> str:
            text = sentence(lo, hi)
            main.append(text)
            close = "" if tag in ("p", "li") and rng.random() < 0.15 else f"</{tag}>"
            return f"<{tag}>{text}{close}"

        def plain(lo: int = 2, hi: int = 14) -> str:
            return rng.choice(("<p>{}</p>", "<div>{}</div>", "<span>{}</span>")).format(sentence(lo, hi))

        junk = {
            "menu": lambda: rng.choice((f"<nav><ul>{links(rng.randint(2, 8))}</ul></nav>", f'<div class="{rng.choice(("menu", "navbar", "breadcrumbs"))}"><ul>{links(4)}</ul></div>', f'<div id="nav">{" | ".join(f"<a href=/>{word()}</a>" for _ in range(4))}</div>')),
            "top": lambda: rng.choice((f"<header><div>{some(1, 3)}</div>{plain(1, 6)}</header>", f'<div class="masthead">{plain(1, 6)}</div>', f'<div id="header"><h2>{some(1, 4)}</h2></div>')),
            "ad": lambda: f'<div class="{rng.choice(("ad", "advert", "ads-box", "sponsored", "promo"))}">{rng.choice((sentence(2, 14), plain(2, 30)))}</div>',
            "side": lambda: rng.choice((f"<aside>{plain()}<ul>{links(3)}</ul>{plain(5, 30)}</aside>", f'<div class="{rng.choice(("sidebar", "related", "widget"))}"><h3>{some(1, 3)}</h3>{plain(5, 30)}<ul>{links(3)}</ul></div>')),
            "notice": lambda: f'<div class="{rng.choice(("cookie-notice", "consent", "newsletter", "popup", "notice"))}">{plain(4, 25)}<button>{word()}</button></div>',
            "form": lambda: f"<form><label>{some(1, 3)}</label><input><p>{sentence(2, 8)}</p><button>{word()}</button></form>",
            "reader": lambda: rng.choice(('<section class="comments">{}</section>', '<div id="comments">{}</div>', '<div class="discussion reader-comments">{}</div>')).format(f"<h3>{some(1, 3)}</h3>" + "".join(f'<div class="comment">{plain(3, 40)}</div>' for _ in range(rng.randint(1, 4)))),
            "share": lambda: f'<div class="share">{links(3)}</div>',
            "bottom": lambda: rng.choice((f"<footer>&copy; {word()} &middot; {sentence(2, 12)}</footer>", f'<div id="footer"><p>&copy; {some(2, 8)}</p><ul>{links(3)}</ul></div>')),
        }
        def cells(tag: str, k: int) -> str:
            return "".join(para(tag, 1, 6) for _ in range(k))

        def rich() -> str:
            """Blocks of articles other than paragraphs, and paragraphs in elements whose names hint at both the text and what surrounds it."""
            return rng.choice((
                lambda: f"<table><tr>{cells('th', 2)}</tr><tr>{cells('td', 2)}</tr></table>",
                lambda: f"<table><caption>{cells('span', 1)}</caption><tbody><tr>{cells('td', 3)}</tr></tbody></table>",
                lambda: para("pre", 2, 30),
                lambda: f"<pre>{para('code', 2, 30)}</pre>",
                lambda: f"<dl>{cells('dt', 1)}{cells('dd', 2)}</dl>",
                lambda: f"<figure><img src=x>{para('figcaption', 2, 12)}</figure>",
                lambda: f"<details>{para('summary', 1, 6)}{para()}</details>",
                lambda: f"<ol>{cells('li', 3)}</ol>",
                lambda: f'<div class="{rng.choice(mixed)}">{para(lo=rng.choice((1, 8)))}{para(lo=5)}</div>',
                lambda: f'<div class="{rng.choice(("row", "wide", "note", "box"))}">{para(lo=1)}</div>',
            ))()

        mixed = ("story-date-tags", "entry-meta-text", "post-top", "text-side", "article-header-text", "main-share", "prose bottom", "story-related-text")
        blocks = [para("h1", 1, 12)] if rng.random() < 0.85 else []
        for _ in range(rng.randint(0 if blocks else 1, 9)):
            kind = rng.random()
            if kind < 0.72:
                blocks.append(para(lo=rng.choice((1, 1, 5, 12))))
            elif kind < 0.8:
                blocks.append(para(rng.choice(("h2", "h3")), 1, 8))
            elif kind < 0.86:
                blocks.append(f"<ul>{''.join(para('li', 1, 12) for _ in range(3))}</ul>")
            elif kind < 0.9:
                blocks.append(f"<blockquote>{para()}</blockquote>")
            elif kind < 0.9 + 0.04 * (rng.random() < 0.8):
                blocks.append(rich())
            elif kind < 0.95:
                text = (some(1, 5), some(1, 3), some(1, 5))
                main.append(" ".join(text))
                blocks.append(f'<p>{text[0]} <a href="/x">{text[1]}</a> {text[2]}</p>')
            else:
                blocks.append(junk[rng.choice(("ad", "share", "side", "form", "notice"))]())
        body = rng.choice(("<article>{}</article>", "<article>{}</article>", "<main>{}</main>", "<main><article>{}</article></main>", '<div class="content">{}</div>', '<div id="post-body">{}</div>', "<div><div>{}</div></div>", '<section class="entry">{}</section>')).format("".join(blocks))
        before = [junk[k]() for k in ("top", "menu", "notice", "ad", "form") if rng.random() < 0.55]
        after = [junk[k]() for k in ("share", "side", "ad", "reader", "form", "notice", "bottom") if rng.random() < 0.5]
        if rng.random() < 0.15:
            before, after = before[:1] if rng.random() < 0.5 else [], []
        page = f"<!DOCTYPE html><html><head><title>{word()}</title><style>p{{}}</style></head><body>{''.join(before)}{body}{''.join(after)}"
        made.append((page + ("</body></html>" if rng.random() < 0.9 else ""), main))
    return made


def labelled_blocks(page: str, main: list[str]) -> tuple[list[tuple[str, ...]], list[int]]:
    """Feature rows and labels of a labelled page."""
    leaves, wanted = leaf_blocks(page), set(main)
    return features(leaves), [int(x.text in wanted) for x in leaves]


@lru_cache(4)
def default_model(pages: int = 240, seed: int = 5) -> ChainModel:
    return train_chain([labelled_blocks(*p) for p in labelled_pages(pages, seed)])


def main_text(page: str | None, model: ChainModel) -> str:
    """The main blocks of a whole page, joined by one space."""
    leaves = leaf_blocks(page or "")
    return " ".join(x.text for x, y in zip(leaves, model.decode(features(leaves)), strict=True) if y)


def extract_main_text(pages: DataFrame, model: ChainModel | None = None) -> DataFrame:
    """page_id, url, text, n_chars for every row of pages.

    Null and empty html, and pages without main text, give the empty text; repeated rows are read each; nulls in page_id and url stay; an empty table gives
    no rows; other columns are ignored. No shuffle."""
    model = model or default_model()
    rows = pick(pages, "page_id", "url", "html").withColumn("html", F.col("html").cast("string"))

    def run(batches):
        for b in batches:
            texts = [main_text(x.as_py(), model) for x in b.column("html")]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    from pyspark.sql import types as T

    kinds = {f.name: f.dataType for f in rows.schema}
    return rows.mapInArrow(run, T.StructType([T.StructField("page_id", kinds["page_id"]), T.StructField("url", kinds["url"]), T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())]))
