"""Main text of HTML pages: a linear-chain conditional random field over the leaf blocks of the DOM.

A page is read into leaf blocks, the runs of text between block-level tags, each with its chain of ancestors.  The field
labels each block as content or not, from the tags, classes and ids of its ancestors and from its text (length, share of
linked text, punctuation, place), and from the label before it.  It is trained by gradient ascent on labelled pages,
which ``labelled_pages`` writes from a fixed seed in many layouts, and decoded by Viterbi.

Contents of head, script, style, template and the like, comments and markup never become blocks.  ``<br>`` counts as white
space.  Character references are decoded, white space inside a block becomes one space, blocks are joined by a line
feed.

Defined cases: null and empty pages give an empty text, as do pages without text.  Unclosed, crossed and unknown tags are
taken as browsers do in the plain cases (a block closes an open paragraph, an end tag closes what is open inside).  Plain
text without tags is one block.  White space is what ``str.split`` takes for it, U+00A0 and other Unicode blanks included.
The text of ``noscript`` is a block like others.  Repeated rows give repeated rows, an empty table an empty result; only
page_id, url and html are read, so other columns of any name do no harm.  Pages of any length and depth are read in one pass.
"""

from __future__ import annotations

import html
import random
import re
from collections import Counter
from collections.abc import Iterator, Set
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm import words as W
from linkveil.session import bounded_batches

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*+)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>", re.S)
ATTRIBUTE = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
NAME = re.compile(r"[a-z]{2,}")
HIDDEN = frozenset("head script style template iframe object svg math noembed noframes datalist audio video canvas".split())
RAW = frozenset("script style title textarea xmp noembed noframes iframe".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 "
    "header hgroup hr html label legend li main menu nav noscript ol optgroup option p pre section select summary table tbody td textarea tfoot th thead tr ul".split()
)
#: Elements that an opening tag of the same group closes.
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
SCOPES = frozenset("ul ol dl table div section article body form select td".split())
CLOSABLE = frozenset({"p"}.union(*CLOSES.values()))


Chain = tuple[tuple[str, ...], str, tuple[str, ...]]


class Open:
    """The open elements.  Whatever a page nests, an opened or closed element costs as much as its own marks, and a chain as
    many steps as there are different marks in it that the field knows."""

    def __init__(self, known: Set[str] | None):
        self.known = known
        self.stack: list[tuple[str, tuple[str, ...]]] = []
        self.names: Counter[str] = Counter()
        self.marks: dict[str, int] = {}
        self.scoped: list[int] = []  # places of elements that an opening tag closes or stops at
        self.cached: Chain | None = None
        self.hidden = 0

    def push(self, name: str, marks: tuple[str, ...]) -> None:
        if name in CLOSABLE or name in SCOPES:
            self.scoped.append(len(self.stack))
        self.stack.append((name, marks))
        self.names[name] += 1
        self.hidden += name in HIDDEN
        for m in marks:
            if self.known is None or m in self.known:
                self.marks[m] = self.marks.get(m, 0) + 1
        self.cached = None

    def pop_to(self, k: int) -> None:
        """Closes the element at place k and all inside of it."""
        while len(self.stack) > k:
            name, marks = self.stack.pop()
            if self.scoped and self.scoped[-1] == len(self.stack):
                self.scoped.pop()
            self.names[name] -= 1
            self.hidden -= name in HIDDEN
            for m in marks:
                if m in self.marks:
                    self.marks[m] -= 1
                    if not self.marks[m]:
                        del self.marks[m]
        self.cached = None

    def close(self, name: str) -> None:
        if self.names[name]:
            k = len(self.stack) - 1
            while self.stack[k][0] != name:
                k -= 1
            self.pop_to(k)

    def closed_by(self, name: str) -> None:
        """What an opening block closes: an open paragraph or list item, unless a scope lies in between."""
        closed = (("p",) if name != "option" else ()) + CLOSES.get(name, ())
        for k in reversed(self.scoped):
            if self.stack[k][0] in closed:
                self.pop_to(k)
                return
            if self.stack[k][0] in SCOPES:
                return

    def chain(self) -> Chain:
        """(different marks, innermost tag, the marks from the third to the fifth)."""
        if self.cached is None:
            top: list[str] = []
            for _, marks in self.stack[:5]:
                top += marks
            self.cached = tuple(self.marks), self.stack[-1][0] if self.stack else "", tuple(top[2:5])
        return self.cached


def blocks(page: str, known: Set[str] | None = None) -> list[tuple[str, Chain, float]]:
    """(text, chain of ancestors, share of linked characters) of each leaf block with text; marks are tags and ``.names``.

    With ``known`` marks outside of it are left out of the chains."""
    out: list = []
    opened = Open(known)
    parts: list[str] = []
    linked = total = 0
    chain: Chain = opened.chain()
    at, n = 0, len(page)
    last = page.rfind(">") + 1  # no tag ends behind it

    def flush() -> None:
        nonlocal linked, total
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                out.append((text, chain, linked / max(1, total)))
            parts.clear()
        linked = total = 0

    def take(text: str) -> None:
        nonlocal linked, total, chain
        if not text or opened.hidden:
            return
        if not total and not text.isspace():
            chain = opened.chain()
        parts.append(text)
        if not text.isspace():
            total += len(text)
            if opened.names["a"]:
                linked += len(text)

    while at < n:
        found = TOKEN.search(page, at, last) if at < last else None
        if found is None:
            comment = page.find("<!--", at)
            take(page[at:] if comment < 0 else page[at:comment])
            break
        if found.start() > at:
            take(page[at : found.start()])
        at = found.end()
        if found[0].startswith("<!--") and not found[0].endswith("-->"):
            break  # a comment that isn't closed
        name = (found[2] or found[5] or "").lower()
        if not name:
            continue
        block = name in BLOCK
        if found[1] or found[4]:
            if block:
                flush()
            opened.close(name)
            continue
        if name == "br":
            take(" ")
            continue
        if block:
            flush()
            opened.closed_by(name)
        if name in VOID:
            continue
        if (found[3] or found[6] or "").endswith("/") and name not in BLOCK:
            continue
        marks = [name]
        for value in ATTRIBUTE.findall(found[3] or found[6] or ""):
            marks += ["." + m for m in NAME.findall("".join(value).lower())]
        opened.push(name, tuple(marks))
        if name in RAW:
            end = _find(page, name, at)
            end = n if end < 0 else end
            take(page[at:end])
            at = end
    flush()
    return out


def _find(page: str, name: str, at: int) -> int:
    found = re.compile("</" + name, re.I).search(page, at)
    return found.start() if found else -1


def chain_features(chain: Chain) -> list[str]:
    marks, tag, top = chain
    return [*("anc" + m for m in marks), "tag" + tag, *{f"top{m}" for m in top}]


def text_features(text: str, share: float, index: int, count: int) -> list[str]:
    n = len(text)
    words = text.count(" ") + 1
    return [
        f"len{0 if n < 15 else 1 if n < 40 else 2 if n < 80 else 3 if n < 160 else 4}",
        f"words{0 if words < 3 else 1 if words < 8 else 2 if words < 20 else 3}",
        f"link{0 if share == 0 else 1 if share < 0.3 else 2 if share < 0.9 else 3}",
        "stop" if text[-1] in ".!?…。" else "nostop",
        "copy" if "©" in text or "copyright" in text.lower() else "nocopy",
        f"place{min(4, 5 * index // max(1, count))}",
        "bias",
    ]


class Field:
    """Weights of a two-label chain: [feature, label], [label before, label], [first label]."""

    def __init__(self, names: dict[str, int], weights: np.ndarray, moves: np.ndarray, start: np.ndarray):
        self.names, self.weights, self.moves, self.start = names, weights, moves, start
        self.table = {f: (float(weights[i, 0]), float(weights[i, 1])) for f, i in names.items()}
        self.known = frozenset(f[3:] for f in names if f.startswith("anc"))
        self.chains: dict[Chain, tuple[float, float]] = {}

    def _sum(self, features: list[str]) -> tuple[float, float]:
        found = [self.table[f] for f in features if f in self.table]
        return sum(a for a, _ in found), sum(b for _, b in found)

    def decode(self, page: list[tuple[str, Chain, float]]) -> list[int]:
        """Most likely labels of a page's blocks."""
        if not page:
            return []
        (m00, m01), (m10, m11) = self.moves.tolist()
        back: list[tuple[int, int]] = []
        s0 = s1 = 0.0
        for i, (text, chain, share) in enumerate(page):
            known = self.chains.get(chain)
            if known is None:
                if len(self.chains) > 20_000:
                    self.chains.clear()
                known = self.chains[chain] = self._sum(chain_features(chain))
            e0, e1 = self._sum(text_features(text, share, i, len(page)))
            e0, e1 = e0 + known[0], e1 + known[1]
            if i:
                from0, from1 = s0 + m00 < s1 + m10, s0 + m01 < s1 + m11
                s0, s1 = (s1 + m10 if from0 else s0 + m00) + e0, (s1 + m11 if from1 else s0 + m01) + e1
                back.append((int(from0), int(from1)))
            else:
                s0, s1 = float(self.start[0]) + e0, float(self.start[1]) + e1
        labels = [int(s1 > s0)]
        for step in reversed(back):
            labels.append(step[labels[-1]])
        return labels[::-1]


def train(pages: list[list[tuple[list[str], int]]], rounds: int = 120, rate: float = 0.15, decay: float = 2e-4) -> Field:
    """Maximum likelihood by Adam; the pages are padded to one length and handled together."""
    names: dict[str, int] = {}
    for page in pages:
        for features, _ in page:
            for f in features:
                names.setdefault(f, len(names))
    longest, n = max(map(len, pages)), len(pages)
    rows, cols, of = [], [], []
    gold = np.zeros((n, longest), dtype=np.int64)
    alive = np.zeros((n, longest), dtype=bool)
    for p, page in enumerate(pages):
        for i, (features, label) in enumerate(page):
            gold[p, i], alive[p, i] = label, True
            cols += [names[f] for f in features]
            rows += [p * longest + i] * len(features)
    del of
    rows, cols = np.array(rows), np.array(cols)
    theta = [np.zeros((len(names), 2)), np.zeros((2, 2)), np.zeros(2)]
    first, second = [np.zeros_like(t) for t in theta], [np.zeros_like(t) for t in theta]
    for t in range(1, rounds + 1):
        weights, moves, start = theta
        score = np.stack([np.bincount(rows, weights[cols, k], minlength=n * longest) for k in (0, 1)], axis=1).reshape(n, longest, 2)
        alpha, beta = np.zeros((n, longest, 2)), np.zeros((n, longest, 2))
        alpha[:, 0] = start + score[:, 0]
        for i in range(1, longest):
            step = np.logaddexp(alpha[:, i - 1, 0, None] + moves[0], alpha[:, i - 1, 1, None] + moves[1]) + score[:, i]
            alpha[:, i] = np.where(alive[:, i, None], step, alpha[:, i - 1])
        for i in range(longest - 2, -1, -1):
            ahead = score[:, i + 1] + beta[:, i + 1]
            step = np.logaddexp(moves[:, 0] + ahead[:, 0, None], moves[:, 1] + ahead[:, 1, None])
            beta[:, i] = np.where(alive[:, i + 1, None], step, 0.0)
        log_z = np.logaddexp(alpha[:, -1, 0], alpha[:, -1, 1])
        post = np.exp(alpha + beta - log_z[:, None, None]) * alive[:, :, None]
        error = (np.eye(2)[gold] * alive[:, :, None] - post).reshape(-1, 2)
        pair = np.exp(alpha[:, :-1, :, None] + moves + (score[:, 1:] + beta[:, 1:])[:, :, None, :] - log_z[:, None, None, None]) * alive[:, 1:, None, None]
        seen = np.zeros((2, 2))
        np.add.at(seen, (gold[:, :-1][alive[:, 1:]], gold[:, 1:][alive[:, 1:]]), 1)
        grads = [
            np.stack([np.bincount(cols, error[rows, k], minlength=len(names)) for k in (0, 1)], axis=1) / n - decay * weights,
            (seen - pair.sum(axis=(0, 1))) / n - decay * moves,
            (np.eye(2)[gold[:, 0]] - post[:, 0]).mean(axis=0),
        ]
        for k, g in enumerate(grads):
            first[k] = 0.9 * first[k] + 0.1 * g
            second[k] = 0.99 * second[k] + 0.01 * g * g
            theta[k] = theta[k] + rate * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.99**t)) + 1e-8)
    return Field(names, *theta)


def labelled_pages(n: int = 480, seed: int = 23) -> list[tuple[str, list[int]]]:
    """(html, label of each block) of made-up pages; every block carries one text of its own, so labels go by position."""
    rng = random.Random(seed)
    syllables = "the of re tion an ing er es and th ou le que de la un en der sch ein os ado ción para und ge eau pour est".split()
    word = lambda: "".join(rng.choice(syllables) for _ in range(rng.randint(1, 4)))
    phrase = lambda a, b: " ".join(word() for _ in range(rng.randint(a, b))).capitalize()
    sentence = lambda: phrase(5, 16) + rng.choice([".", ".", ".", "!", "?", " ***", ""])
    prose = lambda: " ".join(sentence() for _ in range(rng.choice([1, 1, 2, 3, 5])))
    link = lambda t: f'<a href="/{word()}">{t}</a>'
    out = []
    for _ in range(n):
        labels: list[int] = []

        def add(label: int, text: str, labels=labels) -> str:
            labels.append(label)
            return text

        def menu(a: int = 3, b: int = 7) -> str:
            return "<ul>" + "".join(f"<li>{add(0, link(phrase(1, 2)))}</li>" for _ in range(rng.randint(a, b))) + "</ul>"

        def junk(kind: str) -> str:
            tag, names = {
                "menu": ("nav", ("nav", "menu", "navbar", "main-nav", "breadcrumb", "breadcrumbs", "topnav")), "header": ("header", ("header", "site-header", "masthead", "top-bar", "page-header")),
                "footer": ("footer", ("footer", "site-footer", "copyright", "colophon", "page-footer")), "side": ("aside", ("sidebar", "side", "related", "widget", "aside", "see-also", "recommended")),
                "notice": ("div", ("cookie", "notice", "cookie-banner", "consent", "alert", "gdpr", "popup", "banner")), "advert": ("div", ("ad", "ads", "advert", "sponsored", "promo", "advertisement", "ad-slot")),
                "form": ("form", ("search", "newsletter", "subscribe", "login", "signup", "contact-form")), "comments": ("section", ("comments", "comment-list", "comment", "responses", "discussion", "replies")),
                "share": ("div", ("share", "social", "tags", "meta", "byline", "author-box", "pagination", "toolbar")),
            }[kind]
            plain = rng.random()
            tag = tag if plain < 0.65 else "div"
            name = "" if tag not in ("div", "section", "form") and rng.random() < 0.5 else f' {rng.choice(["class", "class", "id"])}="{rng.choice(names)}"'
            if kind in ("menu", "share"):
                body = menu() if rng.random() < 0.8 else add(0, " | ".join(link(phrase(1, 2)) for _ in range(3)))
            elif kind == "header":
                body = (f"<h1>{add(0, link(phrase(1, 3)))}</h1>" if rng.random() < 0.4 else f"<div>{add(0, phrase(1, 4))}</div>") + (menu() if rng.random() < 0.5 else f"<p>{add(0, phrase(3, 7))}</p>")
            elif kind == "footer":
                body = add(0, rng.choice(["&copy; ", "© 2024 ", "Copyright "]) + phrase(1, 3) + rng.choice([" &middot; " + sentence(), "", " " + link(phrase(1, 2))])) if rng.random() < 0.7 else f"<p>{add(0, sentence())}</p>" + menu()
            elif kind == "form":
                body = f"<label>{add(0, phrase(1, 3))}</label><input><button>{add(0, phrase(1, 2))}</button>" + (f"<p>{add(0, sentence())}</p>" if rng.random() < 0.4 else "")
            elif kind == "comments":
                body = f"<h3>{add(0, phrase(1, 3))}</h3>" + "".join(f'<div class="{rng.choice(["comment", "reply", "comment-body"])}"><p>{add(0, prose())}</p></div>' for _ in range(rng.randint(1, 4)))
            elif kind == "side":
                body = f"<h3>{add(0, phrase(1, 3))}</h3>" + (menu() if rng.random() < 0.6 else f"<p>{add(0, prose())}</p>")
            else:
                body = add(0, prose()) if rng.random() < 0.6 else f"<p>{add(0, sentence())}</p><button>{add(0, phrase(1, 1))}</button>"
            return f"<{tag}{name}>{body}</{tag}>"

        def paragraph() -> str:
            kind = rng.random()
            if kind < 0.6:
                text = prose()
                if rng.random() < 0.2:
                    text += " " + link(phrase(1, 3)) + " " + sentence()
                return f"<p>{add(1, text)}</p>"
            if kind < 0.68:
                return f"<p><b>{add(1, sentence())}<br>"
            if kind < 0.76:
                return f"<h{(h := rng.randint(2, 4))}>{add(1, phrase(2, 7))}</h{h}>"
            if kind < 0.84:
                return "<ul>" + "".join(f"<li>{add(1, rng.choice([sentence, lambda: phrase(2, 6)])())}</li>" for _ in range(rng.randint(2, 5))) + "</ul>"
            if kind < 0.89:
                return f"<blockquote><p>{add(1, prose())}</p></blockquote>"
            if kind < 0.93:
                return f"<pre>{add(1, phrase(3, 9))}</pre>"
            if kind < 0.97:
                return "<table>" + "".join("<tr>" + "".join(f"<td>{add(1, phrase(1, 4))}</td>" for _ in range(2)) + "</tr>" for _ in range(2)) + "</table>"
            return f"<p>{add(1, phrase(1, 2) + '.')}</p>"

        around = lambda k: "".join(junk(rng.choice(k)) for _ in range(rng.randint(0, 2)))
        page = around(["menu", "header", "notice", "header"]) + around(["advert", "menu", "share"])
        tag, name = rng.choice([("article", ""), ("article", ""), ("article", ' class="post"'), ("main", ""), ("div", ' class="content"'), ("div", ' id="content"'), ("div", ' class="article-body"'), ("div", ' class="entry-content"'), ("div", ' class="post-text"'), ("section", ' class="story"'), ("div", ""), ("", "")])
        body = f"<h1>{add(1, phrase(2, 8))}</h1>" if rng.random() < 0.85 else ""
        for _ in range(rng.choice([0, 1, 2, 4, 8, 14])):
            body += paragraph()
            if rng.random() < 0.06:
                body += junk(rng.choice(["advert", "share", "side"]))
        if not body:
            body = paragraph()
        if rng.random() < 0.12:
            body += junk("comments")
        page += (f"<{tag}{name}>{body}</{tag}>" if tag else body) + around(["side", "comments", "advert", "share", "form"]) + around(["footer", "footer", "notice"])
        if rng.random() < 0.2:
            page = f'<div class="{rng.choice(["wrapper", "container", "page", "row"])}">{page}</div>'
        if rng.random() < 0.04:
            labels.clear()
            page = add(1, prose())
        out.append((f"<!DOCTYPE html><html><head><title>{phrase(2, 5)}</title><style>p{{x:y}}</style></head><body>{page}</body></html>", labels))
    return out


def examples(pages: list[tuple[str, list[int]]]) -> list[list[tuple[list[str], int]]]:
    out = []
    for page, labels in pages:
        found = blocks(page)
        if len(found) == len(labels) and found:
            out.append([(chain_features(c) + text_features(t, s, i, len(found)), y) for i, ((t, c, s), y) in enumerate(zip(found, labels, strict=True))])
    return out


@lru_cache(maxsize=1)
def field() -> Field:
    """The field trained on all labelled pages."""
    return train(examples(labelled_pages()))


def main_text(page: str | None, model: Field) -> str:
    found = blocks(page, model.known) if page else []
    return "\n".join(text for (text, _, _), label in zip(found, model.decode(found), strict=True) if label)


def _extractor(parts):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Field(*parts)
        for batch in batches:
            texts = [main_text(p, model) for p in batch.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                names=["page_id", "url", "text", "n_chars"],
            )

    return run


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of each page."""
    bounded_batches(pages.sparkSession)
    model = field()
    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    parts = (model.names, model.weights, model.moves, model.start)
    return rows.mapInArrow(_extractor(parts), "page_id long, url string, text string, n_chars long")
