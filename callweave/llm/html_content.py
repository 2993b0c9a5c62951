"""Main text of web pages by a tree-structured graphical model over the DOM.

Block elements are nodes with two states, content or not. A node's potential
comes from its tag, naming hints, text length and link share; an edge's from
the states of parent and child and the child's kind. Sum-product messages go up
and down each tree and give every block its marginal probability of content.
Potentials are fitted by maximum likelihood on labelled pages, which are made
here from templates; nothing depends on the pages to be read.
"""

from __future__ import annotations

import html as html_lib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.tables import spread

# Element names of HTML.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript iframe template title textarea select".split())
#: Drawings and formulas: every element within is inline and may close itself.
FOREIGN = frozenset(("svg", "math"))
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
HOLDERS = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table", "tbody", "thead", "tfoot"}, "td": {"tr", "table"}, "th": {"tr", "table"}}
TAGS = "html body article main section div p h1 h2 h3 h4 h5 h6 ul ol li dl blockquote pre table tbody tr td figure figcaption header footer nav aside form fieldset button head dialog menu details".split()
# Parts of class, id and role names that tell what a block is, or nothing by themselves.
AGAINST = re.compile(r"(?:ads?|adv|advert\w*|banners?|promos?|promotions?|sponsor\w*|nav|navbar|navigation|menus?|breadcrumbs?|header|masthead|topbar|footer|contentinfo|complementary|sidebars?|aside|widgets?|cookies?|consent|notices?|alerts?|popups?|modal|gdpr|comments?|repl(?:y|ies)|respond|disqus|discussion|share|sharing|social|related|recommend\w*|newsletter|subscri\w*|signup|login|search|forms?|pager|pagination|copyright|legal|tags?|toc)")
FOR = re.compile(r"(?:articles?|content|posts?|entry|story|main|body|text|prose|blog)")
NEUTRAL = re.compile(r"(?:\w|\d+\w*|\w*\d+|list|items?|box|bar|block|area|wrap|wrapper|wrapped|container|inner|outer|section|group|row|col|column|site|page|global|top|bottom|left|right|head|foot|title|links?|buttons?|btn|icons?|panel|slot|unit|card|primary|secondary|mobile|desktop|js|md|lg|sm|xs|is|has|the|skip|up|slider?|overlay|media|widget|area|region|module|component|root|view|field|input|meta|info|thread|section)")
WORD = re.compile(r"[a-z]+\d*|\d+")

TOKEN = re.compile(r"<!--.*?(?:--!?>|\Z)|<!\[CDATA\[(.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/<>]*)((?:[^<>\"']++|\"[^\"]*+\"|'[^']*+'|[\"'])*+)>", re.S)
ATTR = re.compile(r"(?<![\w-])(class|id|role|hidden|style|data-y)(?![\w-])(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
#: Hints of a block's names: none, against, for, both, and a word against among others that mean something else.
HINTS = 5
KINDS = 4
LENGTHS, LINKS = (0, 20, 60, 160, 500, 2000), (0.01, 0.2, 0.5, 0.8)
N_FEATURES = 1 + len(TAGS) + 1 + HINTS + (len(LENGTHS) + 1) + (len(LINKS) + 1) + 7


def hint_of(names: str) -> int:
    """What class, id and role names say: each name counts as a whole, so "notice-of-intent" is no notice, but "cookie-notice-2" is."""
    against = good = partly = False
    for name in re.sub(r"([a-z])([A-Z])", r"\1-\2", names).lower().split():
        parts = WORD.findall(name)
        bad = [bool(AGAINST.fullmatch(x)) for x in parts]
        if any(bad):
            known = all(b or FOR.fullmatch(x) or NEUTRAL.fullmatch(x) for x, b in zip(parts, bad))
            against, partly = against or known, partly or not known
        elif any(FOR.fullmatch(x) for x in parts):
            good = True
    return 3 if against and good else 1 if against else 2 if good else 4 if partly else 0


class Page:
    """Blocks of a page in document order: parent, kind of edge, active features, and the runs of text in them."""

    def __init__(self, source: str):
        self.parent, self.tag, self.hint, self.label = [-1], ["html"], [0], [0]
        self.unseen = [False]  # hidden blocks and all below them, which readers don't see
        self.runs: list[tuple[int, str, int]] = []  # block, text, 1 inside a link
        self._read(source)
        self._describe()

    def _open(self, tag, attrs, parent):
        hint, y, unseen = 0, 0, self.unseen[parent]
        if attrs:
            names = ""
            for m in ATTR.finditer(attrs):
                value = m[2] or m[3] or m[4] or ""
                if m[1].lower() == "data-y":
                    y = 1
                elif m[1].lower() == "hidden":
                    unseen = unseen or value.lower() != "until-found"
                elif m[1].lower() == "style":
                    unseen = unseen or bool(UNSEEN.search(value))
                else:
                    names += " " + value
            hint = hint_of(names) if names else 0
        self.unseen.append(unseen)
        self.parent.append(parent)
        self.tag.append(tag)
        self.hint.append(hint)
        self.label.append(y)
        return len(self.parent) - 1

    def _read(self, s):
        stack = [("html", 0)]  # open elements: name, block (inline ones keep their block's)
        held = Counter()  # how often each name is open; every search below costs at most what was pushed
        unclosed = set()  # raw elements without an end tag from here on
        at = 0

        def text(raw):
            if raw:
                self.runs.append((stack[-1][1], html_lib.unescape(raw) if "&" in raw else raw, 1 if held["a"] else 0))

        def push(name, block):
            stack.append((name, block))
            held[name] += 1

        def close(depth):
            for name, _ in stack[depth:]:
                held[name] -= 1
            del stack[depth:]

        for m in TOKEN.finditer(s):
            if m.start() < at:
                continue
            text(s[at : m.start()])
            at = m.end()
            name = m[3]
            if name is None:
                text(m[1])
                continue
            name = name.lower()
            if m[2]:
                if held[name]:
                    depth = next(d for d in range(len(stack) - 1, 0, -1) if stack[d][0] == name)
                    if name in FOREIGN or name not in INLINE or all(n in INLINE for n, _ in stack[depth + 1 :]):
                        close(depth)
                if name not in INLINE and not held["svg"] and not held["math"]:
                    self.runs.append((stack[-1][1], "\n", 0))
                continue
            if name in RAW:
                if not (m[4] or "").endswith("/"):
                    end = None if name in unclosed else re.compile(rf"</{name}(?=[\s/>])[^>]*>", re.I).search(s, at)
                    if end:
                        at = end.end()
                    elif name in ("script", "style", "title", "textarea", "iframe", "noscript"):
                        at = len(s)
                    else:
                        unclosed.add(name)
                self.runs.append((stack[-1][1], " ", 0))
                continue
            if name in VOID:
                if name != "wbr":
                    self.runs.append((stack[-1][1], " ", 0))
                continue
            if name in FOREIGN or held["svg"] or held["math"]:
                if name == "text":
                    self.runs.append((stack[-1][1], " ", 0))
                if not (m[4] or "").endswith("/"):
                    push(name, stack[-1][1])
                continue
            if name in INLINE or name == "object":
                unseen = m[4] and ("hidden" in m[4] or "none" in m[4]) and self._open("div", m[4], stack[-1][1])
                if unseen and not self.unseen[unseen]:
                    for kept in (self.parent, self.tag, self.hint, self.label, self.unseen):
                        kept.pop()
                    unseen = None
                push(name, unseen or stack[-1][1])
                continue
            if name in ("html", "body", "head") and held[name]:
                continue
            drop = ({"p"} if name in CLOSES_P else set()) | SIBLINGS.get(name, set()) | ({"head"} if name == "body" else set())
            if any(held[n] for n in drop):
                stops = HOLDERS.get(name, set())
                for d in range(len(stack) - 1, 0, -1):
                    n = stack[d][0]
                    if n in drop:
                        close(d)
                        if name not in SIBLINGS:
                            break
                    elif n in stops or n not in INLINE and name not in SIBLINGS:
                        break
            self.runs.append((stack[-1][1], "\n", 0))
            push(name, self._open(name, m[4], stack[-1][1]))
        if at < len(s):
            text(s[at:])

    def _describe(self):
        n = len(self.parent)
        chars, linked = [0] * n, [0] * n
        for b, t, a in self.runs:
            k = 0 if self.unseen[b] else len(t.strip())
            chars[b] += k
            linked[b] += k * a
        own = list(chars)
        for b in range(n - 1, 0, -1):
            chars[self.parent[b]] += chars[b]
            linked[self.parent[b]] += linked[b]
        tag_at = {t: i for i, t in enumerate(TAGS)}
        rows, kind = [], []
        inside = [0] * n
        for b in range(n):
            tag, hint = self.tag[b], self.hint[b]
            bad = tag in ("nav", "footer", "aside", "header", "form", "menu", "dialog", "head", "button", "fieldset") or hint == 1
            if b:
                inside[b] = max(inside[self.parent[b]], int(bad))
            share = linked[b] / chars[b] if chars[b] else 0
            base = 1
            feats = [0, base + tag_at.get(tag, len(TAGS))]
            base += len(TAGS) + 1
            feats.append(base + hint)
            base += HINTS
            feats.append(base + sum(chars[b] > x for x in LENGTHS))
            base += len(LENGTHS) + 1
            feats.append(base + sum(share > x for x in LINKS))
            base += len(LINKS) + 1
            feats.append(base + (0 if not own[b] else 1 if inside[b] else 2))
            feats.append(base + 3 + inside[b])
            feats.append(base + 5 + int(share > 0.6 and tag in ("div", "section", "ul", "ol")))
            rows.append(feats)
            kind.append(1 if bad else 2 if tag in ("article", "main") or hint in (2, 3) else 3 if tag in ("p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "blockquote", "pre", "td") else 0)
        self.features, self.kind = rows, kind

    def text(self, wanted) -> str:
        """The wanted blocks' text in page order: white space as one blank, blocks one blank apart."""
        parts, last = [], None
        for b, t, _ in self.runs:
            if wanted[b] and not self.unseen[b]:
                if last is not None and last != b:
                    parts.append(" ")
                parts.append(t)
                last = b
        return " ".join("".join(parts).split())


def forest(pages: list[Page]):
    """All pages' blocks in one array each: features, parents, kinds, and the blocks of each depth."""
    base, feats, parent, kind, depth = 0, [], [], [], []
    for p in pages:
        d = [0] * len(p.parent)
        for b in range(1, len(d)):
            d[b] = d[p.parent[b]] + 1
        feats += p.features
        parent += [x + base if x >= 0 else -1 for x in p.parent]
        kind += p.kind
        depth += d
        base += len(d)
    depth = np.array(depth)
    order = np.argsort(depth, kind="stable")
    levels = np.split(order, np.searchsorted(depth[order], np.arange(1, depth.max() + 1)))
    return np.array(feats), np.array(parent), np.array(kind), levels


def marginals(data, node_weights: np.ndarray, edge: np.ndarray):
    """Probability of content of each block and of the state pairs of each edge, by messages up and down the trees.

    edge[kind, parent's state, own state] are log potentials.
    """
    feats, parent, kind, levels = data
    n = len(parent)
    up = np.zeros((n, 2))
    up[:, 1] = node_weights[feats].sum(axis=1)
    sent = np.zeros((n, 2))
    for at in reversed(levels[1:]):
        sent[at] = np.logaddexp(edge[kind[at], :, 0] + up[at, None, 0], edge[kind[at], :, 1] + up[at, None, 1])
        np.add.at(up, parent[at], sent[at])
    belief, pair = up.copy(), np.zeros((n, 2, 2))
    for at in levels[1:]:
        rest = belief[parent[at]] - sent[at]
        joint = rest[:, :, None] + edge[kind[at]] + up[at][:, None, :]
        belief[at] = np.logaddexp(joint[:, 0], joint[:, 1])
        top = joint.reshape(-1, 4).max(axis=1)[:, None, None]
        pair[at] = np.exp(joint - top)
        pair[at] /= pair[at].sum(axis=(1, 2), keepdims=True)
    return 1 / (1 + np.exp(np.clip(belief[:, 0] - belief[:, 1], -60, 60))), pair


def labelled_pages(n: int = 360, seed: int = 11) -> list[str]:
    """Pages of many layouts; blocks of the article carry data-y, which features never see."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("bcdfghlmnprstvw") + rng.choice("aeiou") for _ in range(rng.randint(1, 4)))
    words = lambda a, b: " ".join(word() for _ in range(rng.randint(a, b)))
    link = lambda: f'<a href="/{word()}">{words(1, 3)}</a>'
    links = lambda k: "<ul>" + "".join(f"<li>{link()}</li>" for _ in range(k)) + "</ul>"
    Y = " data-y"
    HINTED = ["notice", "comment", "header", "form", "menu", "share", "alert", "search", "legal", "banner"]
    named = lambda of: f"{rng.choice(HINTED)}-{of}-{word()}"

    def noise():
        return rng.choice([
            lambda: f"<nav>{links(rng.randint(3, 9))}</nav>",
            lambda: f'<div class="{rng.choice(["menu", "navbar", "breadcrumbs", "top-bar"])}">{links(rng.randint(2, 6))}</div>',
            lambda: f'<div class="{rng.choice(["ad", "advert", "ads", "banner", "promo", "sponsored"])}">{rng.choice([words(3, 40), "<p>" + words(5, 40) + "</p>"])}</div>',
            lambda: f'<aside{rng.choice(["", " class=sidebar"])}><h3>{words(1, 3)}</h3>{rng.choice([links(4), "<p>" + words(10, 60) + "</p>"])}</aside>',
            lambda: f'<div id="{rng.choice(["sidebar", "related", "widget", "share"])}"><h2>{words(1, 3)}</h2><p>{words(5, 50)}</p>{links(2)}</div>',
            lambda: f'<div class="{rng.choice(["cookie-notice", "notice", "alert", "consent", "popup", "newsletter"])}"><p>{words(6, 50)}</p><button>{word()}</button></div>',
            lambda: f"<form><label>{words(1, 4)}</label><input name=q><button>{word()}</button><p>{words(2, 12)}</p></form>",
            lambda: f'<header{rng.choice(["", " class=site-header"])}><h1>{words(1, 5)}</h1><p>{words(3, 15)}</p></header>',
            lambda: f"<div>{' '.join(link() for _ in range(rng.randint(2, 8)))}</div>",
            lambda: f'<div role="{rng.choice(["complementary", "navigation", "contentinfo", "banner", "search"])}"><p>{words(4, 60)}</p></div>',
        ])()

    def comments():
        each = lambda: rng.choice(["<div class=comment><p>{}</p></div>", "<li><p>{}</p></li>", "<p>{}</p>", "<article class=comment><p>{}</p></article>"]).format(words(5, 90))
        return f'<{(t := rng.choice(["section", "div", "ol"]))} {rng.choice(["id=comments", "class=comments", "class=comment-list", "class=replies"])}><h2>{words(1, 3)}</h2>{"".join(each() for _ in range(rng.randint(1, 5)))}</{t}>'

    def block():
        return rng.choice([
            *[lambda: f"<p{Y}>{words(1, 120)}</p>"] * 6,
            lambda: f"<p{Y}>{words(5, 60)} {link()} {words(2, 30)}<br><p{Y}>{words(5, 60)}",
            lambda: f"<h2{Y}>{words(2, 8)}</h2>",
            lambda: f"<ul{Y}>" + "".join(f"<li{Y}>{words(3, 25)}</li>" for _ in range(rng.randint(2, 5))) + "</ul>",
            lambda: f"<blockquote{Y}><p{Y}>{words(8, 50)}</p></blockquote>",
            lambda: f"<pre{Y}>{words(4, 30)}</pre>",
            lambda: f"<table{Y}><tr{Y}><td{Y}>{words(1, 6)}</td><td{Y}>{words(1, 6)}</td></tr></table>",
            lambda: f"<div{Y}>{words(10, 90)}</div>",
            lambda: f"<section{Y}><h3{Y}>{words(1, 5)}</h3><p{Y}>{words(8, 80)}</p></section>",
            lambda: f'<{(t := rng.choice(["p", "p", "section", "div"]))} {rng.choice(["id", "class"])}="{rng.choice([named("of"), named("on"), word() + "-" + rng.choice(HINTED), rng.choice(HINTED) + "-" + word()])}"{Y}>{words(10, 80)}</{t}>',
        ])()

    out = []
    for _ in range(n):
        body = [block() for _ in range(rng.randint(1, 9))]
        for _ in range(rng.choice((0, 0, 1, 1, 2))):
            body.insert(rng.randint(0, len(body)), noise())
        if rng.random() < 0.2:
            body.append(comments())
        tag, attrs = rng.choice([("article", ""), ("article", ""), ("article", ' class="post"'), ("main", ""), ("div", ' class="content"'), ("div", ' id="article-body"'), ("div", ' class="entry-content"'), ("section", ' class="story"'), ("main", ' id="content"')])
        core = f"<{tag}{attrs}{Y}>{rng.choice(['', f'<h1{Y}>{words(2, 12)}</h1>'])}{''.join(body)}</{tag}>"
        if rng.random() < 0.12:  # an article without names or paragraphs
            core = f"<div{Y}>{'<br><br>'.join(words(30, 130) for _ in range(rng.randint(1, 4)))}</div>"
        elif rng.random() < 0.1:
            core = f"<div{Y}>{''.join(body)}</div>"
        if rng.random() < 0.3:
            core = f'<div class="{rng.choice(["wrap", "page", "container", "main"])}">{core}{noise() if rng.random() < 0.5 else ""}</div>'
        before, after = [noise() for _ in range(rng.randint(0, 4))], [noise() for _ in range(rng.randint(0, 2))]
        if rng.random() < 0.35:
            after.append(comments())
        if rng.random() < 0.8:
            after.append(f"<footer>{rng.choice(['&copy; ' + words(2, 20), '<p>' + words(3, 30) + '</p>' + links(3)])}</footer>")
        else:
            after.append(f'<div class="footer"><p>{words(3, 30)}</p></div>')
        out.append(f"<!DOCTYPE html><html><head><title>{words(2, 6)}</title></head><body>{''.join(before)}{core}{''.join(after)}</body></html>")
    return out


def train(sources: list[str], steps: int = 150, rate: float = 0.5, decay: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Node weights and edge potentials of highest (penalised) likelihood of the labelled blocks."""
    pages = [Page(s) for s in sources]
    data = forest(pages)
    y = np.concatenate([p.label for p in pages]).astype(float)
    feats, parent, kind, _ = data
    child = np.flatnonzero(parent >= 0)
    seen = np.zeros((KINDS, 2, 2))
    np.add.at(seen, (kind[child], y[parent[child]].astype(int), y[child].astype(int)), 1)
    w, edge = np.zeros(N_FEATURES), np.zeros((KINDS, 2, 2))
    gw, ge = np.full(N_FEATURES, 1e-6), np.full(edge.shape, 1e-6)
    for _ in range(steps):
        p, pair = marginals(data, w, edge)
        up = np.zeros(N_FEATURES)
        np.add.at(up, feats.ravel(), np.repeat(y - p, feats.shape[1]))
        told = np.zeros(edge.shape)
        np.add.at(told, kind[child], pair[child])
        up, ue = up / len(y) - decay * w, (seen - told) / len(y) - decay * edge
        gw, ge = gw + up**2, ge + ue**2
        w, edge = w + rate * up / np.sqrt(gw), edge + rate * ue / np.sqrt(ge)
    return w, edge


def extract(pages: list[Page], model) -> list[str]:
    """Main texts of parsed pages."""
    p, _ = marginals(forest(pages), *model)
    out, at = [], 0
    for page in pages:
        n = len(page.parent)
        out.append(page.text(p[at : at + n] >= 0.5))
        at += n
    return out


def extract_main_text(pages: DataFrame, model=None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every row, from the whole html; no shuffle.

    Null or empty html and pages without content give an empty text; null ids
    and urls pass; repeated rows stay repeated; character references are decoded.
    """
    model = train(labelled_pages()) if model is None else model

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 64):
                part = b.slice(at, 64)
                texts = extract([Page(h.as_py() or "") for h in part.column(2)], model)
                texts = [t.encode("utf-8", "replace").decode() for t in texts]
                cols = [part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return spread(rows, "page_id").mapInArrow(run, "page_id long, url string, text string, n_chars long")
