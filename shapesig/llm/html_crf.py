"""Main text of web pages by a linear-chain conditional random field over DOM leaf blocks.

A page becomes a sequence of leaf blocks: runs of text that no block-level element
interrupts, each with its chain of ancestors. A block has binary features of its
ancestors' tags, of word parts in their class, id and role attributes, of its
text (length, links, marks, numbers) and of its place. The field has a weight for
each feature and label and for each two labels in a row, trained by gradient on
the log likelihood (forward-backward over padded batches) with a squared penalty,
and is decoded by Viterbi.

The labelled pages are made by ``labelled_pages``: layouts from semantic tags to
nameless division soup, with menus, notices, adverts, forms and comments around
and inside articles. They are fixed by a seed; no page of the input is looked up.

Defined cases: null or empty html gives empty text; scripts, styles, heads and
form controls give no blocks; unclosed tags and comments run to the page's end;
text outside any element is a block; rows that repeat a page_id are extracted
each; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import functools
import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from shapesig.llm.common import rows_of

_OPEN = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9:-]*)")
_SPECIAL = re.compile(r"[>\"']")
_NAMED = re.compile(r"(?:class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.IGNORECASE)
_PARTS = re.compile(r"[a-z]+|[A-Z][a-z]*")

# HTML's element kinds.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template svg math textarea iframe object canvas title".split())
SILENT = frozenset("head select option datalist button".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr br img".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())

TAGS = "article main section nav header footer aside form ul ol li dl dd dt table td th p h1 h2 h3 h4 h5 h6 pre blockquote figure figcaption div body address details dialog fieldset".split()
CUES = {
    "menu": "nav menu navbar navigation breadcrumb breadcrumbs crumbs tabs toc sitemap skip",
    "top": "header masthead topbar head hero logo brand",
    "foot": "footer foot bottom copyright legal colophon imprint",
    "side": "sidebar side aside rail widget widgets secondary complementary",
    "ad": "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion promoted banner teaser affiliate adsense",
    "notice": "notice cookie cookies consent gdpr popup modal overlay alert paywall warning toast disclaimer privacy",
    "form": "form subscribe subscription newsletter signup login search contact register",
    "talk": "comment comments reply replies respond discussion disqus thread reader readers feedback guestbook reviews responses",
    "share": "share sharing social follow related recommend recommended more popular trending pagination pager tags tag meta byline next prev also outbrain taboola links",
    "main": "article content post entry story main body text page prose copy blog news document",
}
_CUE = {w: k for k, ws in CUES.items() for w in ws.split()}

FEATURES = [f"in:{t}" for t in TAGS] + [f"at:{t}" for t in TAGS] + [f"cue:{c}" for c in CUES] + [f"own:{c}" for c in CUES]
FEATURES += [f"chars{k}" for k in range(6)] + [f"links{k}" for k in range(4)] + ["ends", "commas", "sign", "bars", "digits", "capital", "first", "last", "early", "late", "same_parent", "new_parent", "deep", "no_cue", "article+talk", "article+ad", "article+side", "article+form", "article+share", "article+notice", "article+foot", "header_in_article", "article_only", "bias"]
_AT = {f: i for i, f in enumerate(FEATURES)}


_BIT = {w: 1 << i for i, w in enumerate(dict.fromkeys([*TAGS, *CUES, "menu"]))}
_UNDER = {"talk": ("talk",), "ad": ("ad",), "side": ("side", "aside"), "form": ("form",), "share": ("share", "nav", "menu"), "notice": ("notice",), "foot": ("foot", "footer")}
_UNDER_BITS = [(_AT[f"article+{k}"], sum(_BIT[w] for w in ws)) for k, ws in _UNDER.items()]


@dataclass(slots=True)
class Node:
    """An open element: what it and its ancestors are called, as bits, so that a block needs no copy of them."""

    name: str
    tags: int = 0  # its own and its ancestors' tags
    cues: int = 0
    own: int = 0  # its own cues
    within: bool = False  # in an article or the main part
    below: int = 0  # tags and cues below the innermost of these
    depth: int = 0
    path: int = 0  # equal for equal chains of tags


@dataclass(slots=True)
class Block:
    text: str
    node: Node
    linked: float


_TOP = Node("")


class _Marks:
    """Ends of tags in a page. What one scan finds or fails to find is kept, so that all scans together are linear."""

    def __init__(self, page: str):
        self.page = page
        self.special = (0, -1)  # no quote or > from the first place up to the second
        self.closing = (0, -1)
        self.bad: set[int] = set()  # quotes from which no tag ends

    def next_special(self, at: int) -> int:
        if not self.special[0] <= at <= self.special[1]:
            m = _SPECIAL.search(self.page, at)
            self.special = (at, m.start() if m else len(self.page))
        return self.special[1]

    def next_closing(self, at: int) -> int:
        """Place of the next >, or -1."""
        if not self.closing[0] <= at <= self.closing[1]:
            k = self.page.find(">", at)
            self.closing = (at, k if k >= 0 else len(self.page))
        return self.closing[1] if self.closing[1] < len(self.page) else -1

    def tag_end(self, at: int) -> int:
        """Place of the > that ends a tag whose attributes begin here, quotes skipped, or -1."""
        seen = []
        while (k := self.next_special(at)) < len(self.page):
            if self.page[k] == ">":
                return k
            shut = -1 if k in self.bad else self.page.find(self.page[k], k + 1)
            seen.append(k)
            if shut < 0:
                break
            at = shut + 1
        self.bad.update(seen)
        return -1


def blocks(page: str) -> list[Block]:
    """Leaf blocks of a page in order."""
    out: list[Block] = []
    stack: list[Node] = []  # block-level elements; inline ones only count links
    open_at: dict[str, list[int]] = {}  # places in the stack by name
    paths: dict[tuple[int, str], int] = {}
    parts: list[str] = []
    state = {"links": 0, "linked": 0, "chars": 0, "silent": 0}
    marks = _Marks(page)

    def say(raw: str) -> None:
        if raw and not state["silent"]:
            parts.append(raw)
            n = len(raw) - raw.count(" ")
            state["chars"] += n
            if state["links"]:
                state["linked"] += n

    def flush() -> None:
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                out.append(Block(text, stack[-1] if stack else _TOP, state["linked"] / max(1, state["chars"])))
            parts.clear()
        state["chars"] = state["linked"] = 0

    def pop(to: int) -> None:
        while len(stack) > to:
            name = stack.pop().name
            open_at[name].pop()
            state["silent"] -= name in SILENT

    def push(name: str, attrs: str) -> None:
        words = " ".join(x for t in _NAMED.findall(attrs) for x in t) if attrs else ""
        own = sum({_BIT[_CUE[w]] for w in map(str.lower, _PARTS.findall(words)) if w in _CUE})
        up = stack[-1] if stack else _TOP
        bit = _BIT.get(name, 0)
        heads = name in ("article", "main") or own & _BIT["main"] > 0
        path = paths.setdefault((up.path, name), len(paths) + 1)
        open_at.setdefault(name, []).append(len(stack))
        stack.append(Node(name, up.tags | bit, up.cues | own, own, heads or up.within, 0 if heads else up.below | bit | own, up.depth + 1, path))
        state["silent"] += name in SILENT

    at, end = 0, len(page)
    while at < end:
        lt = page.find("<", at)
        if lt < 0:
            say(page[at:])
            break
        say(page[at:lt])
        if page.startswith("<!--", lt):
            shut = page.find("-->", lt + 4)
            at = end if shut < 0 else shut + 3
            continue
        m = _OPEN.match(page, lt)
        shut = marks.tag_end(m.end()) if m else -1
        if shut < 0:
            shut = marks.next_closing(lt) if m or page[lt + 1 : lt + 2] in ("!", "?") else -1
            if shut < 0:
                say("<")
            at = max(lt, shut) + 1
            continue
        name, attrs, at = m[2].lower(), page[m.end() : shut], shut + 1
        if m[1]:
            if name == "a":
                state["links"] = 0
            elif name == "p" and not open_at.get("p"):
                flush()
            elif name not in INLINE and name not in VOID:
                flush()
                if open_at.get(name):
                    pop(open_at[name][-1])
            continue
        if name in RAW:
            if not attrs.rstrip().endswith("/"):
                closed = re.compile(f"</{name}", re.IGNORECASE).search(page, at)
                at = end if not closed else (marks.next_closing(closed.end()) + 1 or end)
            continue
        if name == "br":
            say(" ")
        elif name == "a":
            state["links"] = 1
        elif name not in INLINE:
            flush()
            if name in VOID:
                continue
            if name in CLOSES_P and open_at.get("p"):
                pop(open_at["p"][-1])
            if name in ("li", "dd", "dt", "td", "th", "tr", "option"):
                group = {"li": ("li",), "dd": ("dd", "dt"), "dt": ("dd", "dt"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr", "td", "th"), "option": ("option",)}[name]
                while stack and stack[-1].name in group:
                    pop(len(stack) - 1)
            state["links"] = 0
            push(name, attrs)
    flush()
    return out


@functools.lru_cache(maxsize=4096)
def _named(kind: str, bits: int) -> tuple[int, ...]:
    """Features of the names in ``bits``."""
    return tuple(_AT[f] for w, b in _BIT.items() if bits & b and (f := f"{kind}:{w}") in _AT)


def active(page: list[Block]) -> list[list[int]]:
    """Indices of each block's features."""
    n, out = len(page), []
    for i, b in enumerate(page):
        node, size = b.node, len(b.text)
        f = [_AT["bias"], *_named("in", node.tags), *_named("cue", node.cues), *_named("own", node.own)]
        names = [f"chars{sum(size >= x for x in (15, 40, 80, 160, 320))}", f"links{sum(b.linked > x for x in (0.0, 0.3, 0.7))}"]
        names += [k for k, on in (("ends", b.text[-1] in ".!?:…\"”"), ("commas", "," in b.text), ("sign", "©" in b.text or "®" in b.text), ("bars", "|" in b.text or "»" in b.text or "·" in b.text), ("digits", any(c.isdigit() for c in b.text)), ("capital", b.text[0].isupper()), ("first", i == 0), ("last", i == n - 1), ("early", i < n * 0.2), ("late", i >= n * 0.8), ("deep", node.depth > 7), ("no_cue", not node.cues)) if on]
        if (at := f"at:{node.name}") in _AT:
            names.append(at)
        if i:
            names.append("same_parent" if node.path == page[i - 1].node.path else "new_parent")
        if node.within:
            hit = [k for k, bits in _UNDER_BITS if node.below & bits]
            f += hit
            names += ["header_in_article"] * bool(node.below & _BIT["header"]) + ["article_only"] * (not hit)
        out.append([*f, *(_AT[x] for x in names)])
    return out


@dataclass(frozen=True)
class Field:
    emit: np.ndarray  # features x 2
    step: np.ndarray  # 2 x 2, from label to label

    def decode(self, page: list[Block]) -> list[int]:
        """Viterbi: the likeliest labels (1: main text)."""
        if not page:
            return []
        (a, b), (c, d) = self.step.tolist()
        scores = [self.emit[x].sum(0).tolist() for x in active(page)]
        s0, s1 = scores[0]
        back = []
        for e0, e1 in scores[1:]:
            f0, f1 = s0 + a < s1 + c, s0 + b < s1 + d
            back.append((f0, f1))
            s0, s1 = (s1 + c if f0 else s0 + a) + e0, (s1 + d if f1 else s0 + b) + e1
        labels = [int(s1 > s0)]
        for f in reversed(back):
            labels.append(int(f[labels[-1]]))
        return labels[::-1]


def train(pages: list[tuple[list[Block], list[int]]], rounds: int = 250, penalty: float = 1e-3) -> Field:
    """Weights of largest penalised log likelihood, by Adam on whole batches."""
    pages = [p for p in pages if p[0]]
    n, t, k = len(pages), max(len(p[0]) for p in pages), len(FEATURES)
    x, y, mask = np.zeros((n, t, k), np.float32), np.zeros((n, t), int), np.zeros((n, t), bool)
    for i, (bs, labels) in enumerate(pages):
        for j, f in enumerate(active(bs)):
            x[i, j, f] = 1
        y[i, : len(labels)], mask[i, : len(labels)] = labels, True
    gold = np.eye(2)[y] * mask[..., None]
    pairs = (mask[:, 1:] & mask[:, :-1])[..., None, None]
    gold_step = (np.eye(2)[y[:, :-1]][..., :, None] * np.eye(2)[y[:, 1:]][..., None, :] * pairs).sum((0, 1))
    theta = np.zeros(2 * k + 4)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for r in range(1, rounds + 1):
        emit, step = theta[: 2 * k].reshape(k, 2), theta[2 * k :].reshape(2, 2)
        e = x @ emit
        fwd, bwd = np.zeros((n, t, 2)), np.zeros((n, t, 2))
        fwd[:, 0] = e[:, 0]
        for j in range(1, t):
            fwd[:, j] = np.where(mask[:, j, None], e[:, j] + np.logaddexp(fwd[:, j - 1, :1] + step[0], fwd[:, j - 1, 1:] + step[1]), fwd[:, j - 1])
        for j in range(t - 2, -1, -1):
            nxt = e[:, j + 1] + bwd[:, j + 1]
            bwd[:, j] = np.where(mask[:, j + 1, None], np.logaddexp(step[:, 0] + nxt[:, :1], step[:, 1] + nxt[:, 1:]), bwd[:, j])
        total = np.logaddexp(fwd[:, -1, 0], fwd[:, -1, 1])
        p = np.exp(fwd + bwd - total[:, None, None]) * mask[..., None]
        two = np.exp(fwd[:, :-1, :, None] + step + (e + bwd)[:, 1:, None, :] - total[:, None, None, None]) * pairs
        grad = np.concatenate([np.einsum("ntk,ntl->kl", x, gold - p).reshape(-1), (gold_step - two.sum((0, 1))).reshape(-1)]) / n - penalty * theta
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        theta += 0.08 * (m / (1 - 0.9**r)) / (np.sqrt(v / (1 - 0.999**r)) + 1e-8)
    return Field(theta[: 2 * k].reshape(k, 2), theta[2 * k :].reshape(2, 2))


def labelled_pages(count: int = 420, seed: int = 11) -> list[tuple[list[Block], list[int]]]:
    """Made pages with the label of each block; main text is marked by a private-use character while a page is built."""
    rng = random.Random(seed)
    mark = "\ue000"
    stems = "ba re ti no la ke su mo vi den tor lin gra pes ula ont eri sha kom".split()

    def word() -> str:
        return "".join(rng.choice(stems) for _ in range(rng.randint(1, 4)))

    def line(n: int) -> str:
        s = " ".join(word() + ("," if rng.random() < 0.08 else "") for _ in range(n))
        return s[:1].upper() + s[1:]

    def prose(style: str) -> str:
        out = []
        for _ in range(rng.randint(1, 6)):
            s = line(rng.randint(1, 18))
            out.append({"plain": s + rng.choice("...!?"), "shout": s.upper() + "!!", "symbols": " ".join(w + rng.choice(["***", "%%%", "###"]) for w in s.split()), "bars": s.replace(" ", " | ")}[style])
        return " ".join(out)

    def links(n: int, tag: str = "li") -> str:
        return "".join(f"<{tag}><a href='/{word()}'>{line(rng.randint(1, 3))}</a></{tag}>" for _ in range(n))

    def pick(*names: str) -> str:
        return rng.choice(names)

    def attr(*names: str) -> str:
        name = pick(*names)
        return f' {pick("class", "class", "id")}="{pick("", "site-", "c-", "wp-", "js_")}{name}{pick("", "-1", "-box", "__inner")}"'

    def short(lo: int = 1, hi: int = 14) -> str:
        return line(rng.randint(lo, hi)) + pick(".", "", ".", "!")

    def noise(kind: str) -> str:
        body = {
            "menu": lambda: pick(f"<nav{pick('', attr('menu'))}><ul>{links(rng.randint(2, 8))}</ul></nav>", f"<div{attr('nav', 'menu', 'navbar', 'breadcrumbs')}>{links(rng.randint(2, 7), pick('span', 'div', 'li'))}</div>", f"<ul{attr('menu', 'nav')}>{links(rng.randint(3, 8))}</ul>"),
            "top": lambda: pick(f"<header><{(t := pick('h1', 'div', 'p'))}>{short(1, 5)}</{t}>{pick('', '<p>' + short() + '</p>')}</header>", f"<div{attr('header', 'masthead', 'topbar')}><a href='/'>{short(1, 4)}</a><p>{short()}</p></div>"),
            "foot": lambda: pick(f"<footer>&copy; {word()}.example &middot; {prose('plain')}</footer>", f"<footer><p>{short()}</p><ul>{links(rng.randint(1, 5))}</ul></footer>", f"<div{attr('footer', 'foot', 'copyright', 'legal')}><p>&copy; 20{rng.randint(10, 26)} {short()}</p>{prose('plain')}</div>"),
            "side": lambda: pick(f"<aside>{pick('<h3>' + short(1, 4) + '</h3>', '')}<p>{prose('plain')}</p><ul>{links(rng.randint(0, 5))}</ul></aside>", f"<div{attr('sidebar', 'widget', 'rail', 'related', 'popular')}><h3>{short(1, 4)}</h3><ul>{links(rng.randint(2, 6))}</ul><p>{short()}</p></div>"),
            "ad": lambda: f"<{(t := pick('div', 'div', 'section', 'aside', 'p'))}{attr('ad', 'ads', 'advert', 'sponsored', 'promo', 'banner')}>{pick(prose('plain'), short(), '<p>' + prose('plain') + '</p>', '<a href=/x>' + short() + '</a>')}</{t}>",
            "notice": lambda: f"<{(t := pick('div', 'div', 'section', 'p', 'dialog'))}{attr('notice', 'cookie', 'consent', 'cookie-banner', 'popup', 'alert', 'gdpr', 'paywall')}>{pick(short(), prose('plain'), '<p>' + prose('plain') + '</p><button>OK</button>')}</{t}>",
            "form": lambda: pick(f"<form action='/s'>{pick('<label>' + short(1, 4) + '</label>', '<p>' + prose('plain') + '</p>')}<input name=q><button>{word()}</button></form>", f"<div{attr('newsletter', 'subscribe', 'signup', 'login')}><p>{prose('plain')}</p><form><label>{short(1, 3)}</label><input></form></div>"),
            "talk": lambda: f"<{(t := pick('section', 'div', 'div', 'ol', 'aside'))}{attr('comments', 'comment', 'replies', 'discussion', 'respond', 'reader-comments')}>{pick('<h3>' + short(1, 4) + '</h3>', '')}" + "".join(f"<{(u := pick('div', 'p', 'li', 'article'))}{pick('', attr('comment', 'reply'))}>{pick('<b>' + word() + '</b> ', '')}{pick('<p>' + prose('plain') + '</p>', prose('plain'))}</{u}>" for _ in range(rng.randint(1, 5))) + f"</{t}>",
            "share": lambda: f"<{(t := pick('div', 'ul', 'p'))}{attr('share', 'social', 'related', 'tags', 'pagination', 'meta', 'byline', 'recommended')}>{pick(links(rng.randint(2, 5), 'span'), short(1, 6))}</{t}>",
        }
        return body[kind]()

    def article() -> str:
        style = rng.choices(["plain", "shout", "symbols", "bars"], [6, 1, 1, 1])[0]

        def p() -> str:
            open_b, shut_b = pick(("", ""), ("", ""), ("<b>", ""), ("<b>", "</b>"), ("<a href='#'>", "</a>"), ("<em>", "</em>"))
            return f"<p>{open_b}{mark}{pick('', line(1) + ' ')}{shut_b}{prose(style)}{pick('</p>', '</p>', '</p>', '<br>')}"

        items = [p for _ in range(rng.randint(1, 9))]
        for extra, chance in ((lambda: f"<h2>{mark}{short(1, 7)}</h2>", 0.4), (lambda: "<ul>" + "".join(f"<li>{mark}{short(2, 15)}</li>" for _ in range(rng.randint(2, 5))) + "</ul>", 0.25), (lambda: f"<blockquote>{pick('', '<p>')}{mark}{prose(style)}</blockquote>", 0.2), (lambda: f"<pre>{mark}{short(3, 9)}</pre>", 0.1), (lambda: "<table><tr>" + "".join(f"<td>{mark}{short(1, 4)}</td>" for _ in range(rng.randint(2, 6))) + "</tr></table>", 0.12), (lambda: f"<figure><img src=x><figcaption>{mark}{short(2, 9)}</figcaption></figure>", 0.12), (lambda: f"<div>{mark}{prose(style)}</div>", 0.15)):
            if rng.random() < chance:
                items.insert(rng.randint(0, len(items)), extra)
        inner = [f() for f in items]
        for kind in ("ad", "notice", "form", "side", "share"):
            if rng.random() < 0.2:
                inner.insert(rng.randint(0, len(inner)), noise(kind))
        head = f"<h1>{mark}{line(rng.randint(2, 9))}</h1>"
        head = pick(head, head, head, f"<header>{head}</header>", "", f"<h2>{mark}{short(2, 8)}</h2>")
        tail = (noise("talk") if rng.random() < 0.25 else "") + (noise("share") if rng.random() < 0.15 else "") + (noise("foot") if rng.random() < 0.08 else "")
        whole = head + "".join(inner) + tail
        shell = rng.random()
        if shell < 0.45:
            return f"<article>{whole}</article>"
        if shell < 0.6:
            return f"<main>{pick(whole, '<article>' + whole + '</article>', '<div>' + whole + '</div>')}</main>"
        if shell < 0.9:
            return f"<div{attr('content', 'article', 'post', 'entry-content', 'story', 'main', 'article-body')}>{whole}</div>"
        return f"<div>{whole}</div>"

    def page() -> str:
        before = [noise(k) for k, c in (("top", 0.4), ("menu", 0.8), ("notice", 0.35), ("ad", 0.5), ("form", 0.15), ("side", 0.1)) if rng.random() < c]
        rng.shuffle(before)
        after = [noise(k) for k, c in (("talk", 0.35), ("share", 0.2), ("side", 0.35), ("ad", 0.3), ("form", 0.2), ("notice", 0.15)) if rng.random() < c]
        rng.shuffle(after)
        body = "".join(before) + article() + "".join(after) + (noise("foot") if rng.random() < 0.85 else "")
        if rng.random() < 0.12:  # a page of an article alone, often a short one
            body = pick(article(), f"<article>{pick('', f'<h1>{mark}{short(1, 4)}</h1>')}<p>{mark}{short(1, 6)}</p></article>")
        return f"<!DOCTYPE html><html><head><title>{short()}</title><style>p{{}}</style></head><body>{pick(body, body, '<div>' + body + '</div>')}{pick('</body></html>', '')}"

    out = []
    for _ in range(count):
        bs = blocks(page())
        labels = [int(mark in b.text) for b in bs]
        for b in bs:
            b.text = " ".join(b.text.replace(mark, "").split()) or "-"
        out.append((bs, labels))
    return out


@functools.lru_cache(maxsize=1)
def field() -> Field:
    return train(labelled_pages())


def main_text(page: str, model: Field) -> str:
    found = blocks(page)
    return "\n".join(b.text for b, keep in zip(found, model.decode(found), strict=True) if keep)


def extract(pages: DataFrame, model: Field | None = None) -> DataFrame:
    """page_id, url, text and its code points for every page."""
    model = model or field()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in rows_of(batch, "html"):
                texts = [main_text(x, model) if x else "" for x in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
