"""Leaf blocks of an HTML page, and labelled synthetic pages to learn from."""

from __future__ import annotations

import html
import re
from dataclasses import dataclass, field

import numpy as np

# Element names of HTML by how they nest.
BLOCK_TAGS = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html label legend li main menu nav ol optgroup option p pre search section select "
    "summary table tbody td tfoot th thead title tr ul".split()
)
VOID_TAGS = frozenset("area base basefont bgsound br col embed frame hr img input keygen link meta param source track wbr".split())
HIDDEN_TAGS = frozenset("script style template svg iframe object canvas audio video noframes noembed head title".split())
CLOSES_P = BLOCK_TAGS - frozenset("body button caption dd dt head html label legend li optgroup option select tbody td tfoot th thead title tr".split())
# Elements that may stand in a head; elements whose content is no markup; those of a drawing that hold text or markup again.
HEAD_TAGS = frozenset("base basefont bgsound head html link meta noframes noscript script style template title".split())
RAW_TAGS = ("script", "style", "textarea", "title", "iframe", "noembed", "noframes")
DRAWING_TEXT = frozenset("foreignobject desc title".split())
INLINE_HTML = frozenset("b big br code em embed i img s small span strike strong sub sup tt u var".split())

# A tag is its name and attributes. A quote opens a value only straight after the equals sign; elsewhere it is a letter like others.
_BLANK = r"[ \t\n\f\r]"
_VALUE = rf"{_BLANK}*+=({_BLANK}*+)(?:\"([^\"]*+)(?:\"|\Z)|'([^']*+)(?:'|\Z)|([^ \t\n\f\r>\"'][^ \t\n\f\r>]*+))?+"
_ATTRIBUTE = rf"(=?+[^ \t\n\f\r/>=]++|=)(?:{_VALUE})?+"
_TAG = rf"</?[a-zA-Z][^ \t\n\f\r/>]*+(?:[ \t\n\f\r/]++|{re.sub(r'(?<!\\)[(](?![?])', '(?:', _ATTRIBUTE)})*+(?:>|\Z)"
_TOKEN = re.compile(rf"<!--(?:-?>|.*?(?:--!?>|\Z))|{_TAG}|<[!?/][^>]*+(?:>|\Z)|[^<]++|<", re.S)
_NAME = re.compile(r"<(/?)([a-zA-Z][^ \t\n\f\r/>]*)")
_MARKS = re.compile(_ATTRIBUTE, re.S)
_MARKED = re.compile("class|id|role|data-y", re.I)
_RAW = {t: re.compile(rf"</{t}(?=[ \t\n\f\r/>]|\Z)[^>]*(?:>|\Z)", re.I) for t in RAW_TAGS}
_PART = re.compile(r"[a-z]+")


@dataclass
class Block:
    path: tuple[str, ...]
    text: str
    linked: int
    label: int = 0
    elements: list[str] = field(default_factory=list)


def marks_of(tag: str, at: int) -> dict[str, str]:
    """class, id, role and data-y of a tag, from place `at` on; of an attribute given twice the first counts."""
    found: dict[str, str] = {}
    if _MARKED.search(tag, at):
        for m in _MARKS.finditer(tag, at, len(tag) - 1):
            name = m[1].lower()
            if name in ("class", "id", "role", "data-y") and m[2] is not None:
                found.setdefault(name, html.unescape(m[3] or m[4] or m[5] or "").lower())
    return found


def blocks_of(page: str | None) -> list[Block]:
    """The page's runs of text between block tags, white space as single blanks; nothing of scripts, styles or the head."""
    page = page or ""
    stack: list[tuple[str, tuple[str, ...], str]] = []
    found: list[Block] = []
    texts: list[str] = []
    linked = hidden = anchors = drawings = 0

    def flush() -> None:
        nonlocal linked
        if texts:
            text = " ".join("".join(texts).split())
            if text:
                label = next((y for _, _, y in reversed(stack) if y), "0")
                path = tuple(e for _, elements, _ in stack for e in elements)
                found.append(Block(path, text, linked, int(label == "1")))
            texts.clear()
        linked = 0

    def pop(to: int) -> None:
        nonlocal hidden, anchors, drawings
        while len(stack) > to:
            tag = stack.pop()[0]
            hidden -= tag in HIDDEN_TAGS
            anchors -= tag == "a"
            drawings -= tag in ("svg", "math")

    def out_of(tag: str) -> None:
        """End the drawings that an HTML element can't stand in, and the head where it can't."""
        for i in range(len(stack) - 1, -1, -1):
            if stack[i][0] in DRAWING_TEXT:
                break
            if stack[i][0] in ("svg", "math"):
                pop(i)
                break
        if stack and stack[-1][0] == "head" and tag not in HEAD_TAGS:
            pop(len(stack) - 1)

    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.match(page, at)
        at = m.end()
        token = m[0]
        if token[0] != "<" or token == "<":
            if hidden and stack[-1][0] == "head" and not token.isspace():
                pop(len(stack) - 1)
            if not hidden:
                texts.append(html.unescape(token) if "&" in token else token)
                if anchors:
                    linked += len(token)
            continue
        name = _NAME.match(token)
        if not name or not token.endswith(">"):  # comments, declarations, a tag cut off by the end
            continue
        tag = name[2].lower()
        if name[1]:
            if tag in BLOCK_TAGS:
                flush()
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == tag:
                    pop(i)
                    break
                if stack[i][0] in BLOCK_TAGS and tag not in BLOCK_TAGS:
                    break
            continue
        if drawings and (tag in BLOCK_TAGS or tag in INLINE_HTML) or stack and stack[-1][0] == "head":
            out_of(tag)
        if tag in BLOCK_TAGS:
            flush()
            if tag in CLOSES_P or tag in ("li", "dd", "dt", "td", "th", "tr", "option"):
                ends = "p" if tag in CLOSES_P else tag
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] == ends:
                        pop(i)
                        break
                    if stack[i][0] in BLOCK_TAGS and stack[i][0] not in ("p", "dd", "dt", "td", "th"):
                        break
            if tag == "body":
                pop(next((i for i, e in enumerate(stack) if e[0] == "head"), len(stack)))
        elif tag == "br":
            texts.append(" ")
        if tag in VOID_TAGS or token.endswith("/>") and (drawings or tag in ("svg", "math")):
            continue
        if tag in ("script", "style") or tag in _RAW and not drawings:
            end = _RAW[tag].search(page, at)
            at = end.end() if end else size
            continue
        marks = marks_of(token, name.end()) if len(token) > len(tag) + 2 else {}
        elements = (tag, *(f"{k}:{part}" for k in ("class", "id", "role") if k in marks for part in _PART.findall(marks[k])))
        stack.append((tag, elements, marks.get("data-y", "")))
        hidden += tag in HIDDEN_TAGS
        anchors += tag == "a"
        drawings += tag in ("svg", "math")
    flush()
    return found


# Names that pages commonly give to the parts around an article and to the article.
AROUND = {
    "nav": ["nav", "menu", "navbar", "navigation", "breadcrumb", "topnav", "main-menu", "tabs", "pagination"],
    "header": ["header", "masthead", "site-header", "topbar", "banner", "logo", "branding"],
    "footer": ["footer", "site-footer", "bottom", "copyright", "colophon", "legal", "imprint"],
    "aside": ["sidebar", "side", "widget", "related", "trending", "popular", "recommended", "tags", "archive", "teaser", "more"],
    "ad": ["ad", "ads", "advert", "advertisement", "sponsored", "promo", "promotion", "banner-ad", "adsense"],
    "notice": ["cookie", "cookies", "notice", "consent", "gdpr", "alert", "newsletter", "subscribe", "paywall", "popup", "modal", "overlay"],
    "form": ["form", "search", "login", "signup", "contact-form", "register"],
    "comments": ["comments", "comment", "comment-list", "responses", "disqus", "replies", "discussion", "reader-comments", "user-comment"],
    "share": ["share", "social", "sharing", "follow", "toolbar", "buttons"],
}
ARTICLE = ["article", "post", "content", "entry", "entry-content", "post-body", "story", "article-body", "main-content", "text", "body-copy"]


class PageMaker:
    """Random pages of many layouts; an element's data-y tells whether its text belongs to the article."""

    def __init__(self, seed: int = 11):
        self.rng = np.random.default_rng(seed)
        letters = "abcdefghijklmnopqrstuvwxyz"
        self.words = ["".join(self.pick(letters) for _ in range(self.rng.integers(1, 11))) for _ in range(3000)]

    def pick(self, options):
        return options[int(self.rng.integers(len(options)))]

    def chance(self, p: float) -> bool:
        return self.rng.random() < p

    def said(self, low: int, high: int) -> str:
        style = self.rng.integers(8)
        out = []
        for _ in range(int(self.rng.integers(low, high + 1))):
            w = self.pick(self.words)
            out.append(w.upper() + "!!" if style == 0 else w + self.pick(["***", "$$$", "%%%", "&amp;&amp;"]) if style == 1 else w + " |" if style == 2 else w)
        text = " ".join(out)
        if style > 2:
            text = re.sub(r"(\w+ \w+ \w+ \w+) (\w)", lambda m: m[1] + self.pick([", ", ". ", " ", " "]) + m[2], text)
        return text[:1].upper() + text[1:] + self.pick([".", ".", ".", "", "!"])

    def links(self, n: int) -> str:
        items = [f'<a href="/{self.pick(self.words)}">{self.said(1, 3).rstrip(".!")}</a>' for _ in range(n)]
        return "<ul>" + "".join(f"<li>{i}</li>" for i in items) + "</ul>" if self.chance(0.7) else self.pick([" ", " | ", "<br>"]).join(items)

    def prose(self, low: int, high: int) -> str:
        inner = self.said(low, high)
        if self.chance(0.2):
            inner = f"<b>{inner}<br>" if self.chance(0.5) else f'{inner} <a href="/x">{self.said(1, 3)}</a> {self.said(3, 20)}'
        if self.chance(0.02):
            inner = f"{inner} <math><mi>{self.said(1, 1)}</mi><mo>=</mo><mn>2</mn></math> {self.said(1, 5)}"
        said = f"<p>{inner}" + "</p>" * self.chance(0.9)
        return f"<noscript>{said}</noscript>" if self.chance(0.01) else said

    def around(self, kind: str) -> str:
        name = self.pick(AROUND[kind])
        mark = f' {self.pick(["class", "class", "id"])}="{name}"'
        tag = {"nav": "nav", "header": "header", "footer": "footer", "aside": "aside", "form": "form"}.get(kind, "div")
        if self.chance(0.4):
            tag = self.pick(["div", "section"])
        elif self.chance(0.6) and tag != "div":
            mark = ""
        if kind == "nav":
            inner = self.links(int(self.rng.integers(2, 12)))
        elif kind == "footer":
            inner = self.pick(["&copy; ", "", "Copyright 2020 "]) + self.said(3, 25) + (self.links(3) if self.chance(0.4) else "")
        elif kind == "comments":
            inner = "".join(f'<div class="{self.pick(["comment", "reply", "user"])}"><p>{self.said(2, 60)}</p></div>' for _ in range(int(self.rng.integers(1, 6))))
            inner = self.pick(["<h3>Comments</h3>", "<h2>Responses</h2>", ""]) + inner
        elif kind == "form":
            inner = f"<label>{self.said(1, 3)}</label><input name=q><button>{self.said(1, 2)}</button>"
        elif kind in ("ad", "notice"):
            inner = self.said(2, 40) if self.chance(0.6) else f"<p>{self.said(2, 40)}</p>" + (f"<button>{self.said(1, 2)}</button>" if self.chance(0.4) else "")
        elif kind == "header":
            inner = f'<a href="/">{self.said(1, 3)}</a>' + (f"<p>{self.said(2, 8)}</p>" if self.chance(0.5) else "")
        else:
            inner = (f"<h4>{self.said(1, 3)}</h4>" if self.chance(0.6) else "") + (self.links(4) if self.chance(0.6) else f"<p>{self.said(3, 30)}</p>")
        whole = f'<{tag}{mark} data-y="0">{inner}</{tag}>'
        return f"<noscript>{whole}</noscript>" if kind == "notice" and self.chance(0.3) else whole

    def article(self) -> str:
        rng, parts = self.rng, []
        if self.chance(0.9):
            title = f"<h1>{self.said(2, 12)}</h1>"
            parts.append(f"<header>{title}</header>" if self.chance(0.1) else title)
        for _ in range(int(min(40, rng.geometric(0.12))) if self.chance(0.9) else 1):
            kind = rng.random()
            if kind < 0.78:
                parts.append(self.prose(*self.pick([(1, 1), (1, 3), (1, 12), (5, 90), (5, 90), (20, 90), (60, 300)])))
            elif kind < 0.86:
                parts.append(f"<h{rng.integers(2, 5)}>{self.said(1, 8)}</h2>")
            elif kind < 0.91:
                parts.append("<ul>" + "".join(f"<li>{self.said(2, 15)}</li>" for _ in range(rng.integers(2, 6))) + "</ul>")
            elif kind < 0.94:
                parts.append(f"<blockquote>{self.said(5, 40)}</blockquote>")
            elif kind < 0.96:
                parts.append(f"<table><tr><td>{self.said(1, 3)}</td><td>{self.said(1, 3)}</td></tr></table>")
            else:
                parts.append(self.around(self.pick(["ad", "share", "aside"])))
        if self.chance(0.12):
            parts.append(self.around("comments"))
        tag, mark = ("article", "") if self.chance(0.6) else ("main", "") if self.chance(0.3) else ("div", f' class="{self.pick(ARTICLE)}"')
        if tag == "article" and self.chance(0.2):
            mark = f' class="{self.pick(ARTICLE)}"'
        return f'<{tag}{mark} data-y="1">{"".join(parts)}</{tag}>'

    def page(self) -> str:
        before = [self.around(k) for k in ("header", "nav", "notice", "ad", "aside", "form", "share") if self.chance({"nav": 0.85, "header": 0.4, "ad": 0.5}.get(k, 0.2))]
        after = [self.around(k) for k in ("share", "comments", "aside", "ad", "notice", "form", "footer") if self.chance({"footer": 0.9, "comments": 0.35, "aside": 0.35}.get(k, 0.15))]
        if self.chance(0.3):
            self.rng.shuffle(before)
        inner = "".join([*before, self.article(), *after])
        if self.chance(0.3):
            inner = f'<div {self.pick(["id", "class"])}="{self.pick(["page", "wrapper", "container", "site", "layout"])}">{inner}</div>'
        whole = f"<!DOCTYPE html><html><head><title>{self.said(2, 8)}</title></head><body>{inner}</body></html>"
        return whole[: int(len(whole) * self.rng.uniform(0.4, 1))] if self.chance(0.15) else whole
