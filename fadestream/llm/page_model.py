r"""The DOM of a page as a tree of blocks, and a binary graphical model on it.

Nodes are block elements and the runs of text in them; inline markup belongs to its run. Each node has a hidden label,
content or not, a potential from its own features, and a potential with its parent's label. Sum-product messages, first
from the leaves up, then from the root down, give the exact marginals; both the inference and the gradient of the log
likelihood work on many pages at once, one level of depth at a time. Weights come from labelled pages that a seeded
generator writes (varied layouts, class names and junk), so training needs no outside data.
"""

from __future__ import annotations

import functools
import html as entities
import random
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np

# Repeats are possessive: a tag is closed by the first > outside quotes or not at all, so nothing is tried twice.
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+(?:>|\Z)|<(script|style|noscript|template|textarea|title|svg|iframe|select|button|object)\b(?:\"[^\"]*+\"|'[^']*+'|[^'\">])*+>.*?(?:</\1\s*+>|\Z)"
    r"|<(/?)([a-zA-Z][^\s/>]*+)((?:\"[^\"]*+\"|'[^']*+'|[^'\">]++)*+)>|[^<]++|<",
    re.S | re.I,
)
_NAMED = re.compile(r"</?[a-zA-Z][^\s/>]*+")
_EVENT = re.compile("[\"'>]")
_ATTR = re.compile(r"(?:class|id|role|aria-label|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|/|$)|display\s*:\s*none|aria-hidden\s*=\s*[\"']?true", re.I)
_WORD = re.compile(r"[a-z]+")

INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr input meta link source".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
P_CLOSERS = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul figure details".split())
SAME_CLOSERS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
STOPPERS = frozenset("ul ol dl table body html div section article td th blockquote main aside nav header footer form".split())
_MARKED = STOPPERS | {"p"} | frozenset(x for names in SAME_CLOSERS.values() for x in names)
#: Levels of a tree; what is nested deeper hangs at the last one, as in browsers.
DEEPEST = 512

TAGS = ["nav", "header", "footer", "aside", "form", "article", "main", "section", "div", "ul", "ol", "dl", "li", "p", "h1", "h2", "h3", "table", "blockquote", "pre", "figure", "body", "html", "#text"]
_TAG_AT = {t: i for i, t in enumerate(TAGS)} | {"h4": 16, "h5": 16, "h6": 16, "tr": 17, "td": 17, "th": 17, "tbody": 17, "dt": 12, "dd": 12, "figcaption": 20, "fieldset": 4, "menu": 0}
GROUPS = [
    "ad ads advert advertisement adsense banner sponsor sponsored promo promotion",
    "nav navbar navigation menu breadcrumb breadcrumbs toc pagination pager topbar toolbar",
    "comment comments reply replies discussion disqus responses respond",
    "footer foot copyright legal colophon bottom",
    "header masthead head brand logo top site",
    "sidebar side aside widget related recommended more popular trending rail",
    "cookie cookies consent notice alert gdpr popup modal overlay message warning",
    "share social subscribe newsletter signup login search follow tags meta",
    "article content post entry story main body text page prose read",
]
_GROUP_AT = {w: i for i, g in enumerate(GROUPS) for w in g.split()}
#: Kinds of nodes with potentials of their own towards their parents: others, texts, article-like, aside-like, generic boxes.
_KIND = {"#text": 1, "article": 2, "main": 2, "nav": 3, "header": 3, "footer": 3, "aside": 3, "form": 3, "div": 4, "section": 4}
KINDS = 5
N_FEATURES = len(TAGS) + len(GROUPS) + 9
TEXT = "#text"


def _closing(source: str, start: int) -> tuple[list[int], list[bool]]:
    """Places of quotes and > from start on; for each, whether a tag that reaches it outside quotes is ever closed. One pass, from the right."""
    events = list(_EVENT.finditer(source, start))
    at, closed = [m.start() for m in events], [False] * (len(events) + 1)
    later = {}  # the nearest quote of either kind to the right
    for i in range(len(events) - 1, -1, -1):
        c = events[i].group()
        if c == ">":
            closed[i] = True
        else:
            closed[i] = c in later and closed[later[c] + 1]
            later[c] = i
    return at, closed


def tokens(source: str) -> Iterator[re.Match]:
    """Matches of _TOKEN from end to end in time linear in the page. A < that opens a tag which nothing closes is text; from the
    first of those on, a table says which tags are closed."""
    pos = None
    for m in _TOKEN.finditer(source):
        if m.end() - m.start() == 1 and _NAMED.match(source, m.start()):
            pos = m.start()
            break
        yield m
    if pos is None:
        return
    at, closed = _closing(source, pos)
    alone = re.compile("<")
    while pos < len(source):
        name = _NAMED.match(source, pos)
        m = (alone if name and not closed[bisect_left(at, name.end())] else _TOKEN).match(source, pos)
        yield m
        pos = m.end()


class _Stack:
    """Open blocks (name, node); closers are looked up by count and by the few that bound a search, so no step walks a deep stack twice."""

    def __init__(self) -> None:
        self.open: list[tuple[str, int]] = [("html", 0)]
        self.count: Counter = Counter()
        self.marks: list[int] = []

    def push(self, name: str, node: int) -> None:
        if name in _MARKED:
            self.marks.append(len(self.open))
        self.open.append((name, node))
        self.count[name] += 1

    def cut(self, at: int) -> None:
        for name, _ in self.open[at:]:
            self.count[name] -= 1
        del self.open[at:]
        while self.marks and self.marks[-1] >= at:
            self.marks.pop()

    def close(self, name: str) -> bool:
        """An end tag: everything up to the innermost block of that name goes."""
        if not self.count[name]:
            return False
        self.cut(next(i for i in range(len(self.open) - 1, 0, -1) if self.open[i][0] == name))
        return True

    def imply(self, names: set[str]) -> None:
        """A start tag that ends an open block of one of these names, if no stopper is in between."""
        for i in reversed(self.marks):
            if self.open[i][0] in names:
                self.cut(i)
                return
            if self.open[i][0] in STOPPERS:
                return


class Page:
    """Nodes of one page: parent, tag number, features; runs of text by node."""

    __slots__ = ("depth", "features", "parent", "runs")

    def __init__(self, source: str) -> None:
        self.parent: list[int] = []
        self.depth: list[int] = []
        self.runs: list[tuple[int, str]] = []
        self._build(source)

    def _build(self, source: str) -> None:
        tags, words_of_class, dark = ["html"], [set()], [False]
        self.parent, self.depth = [-1], [0]
        stack = _Stack()
        run: list[str] = []
        linked = 0
        stats: dict[int, tuple[int, int]] = {}

        def add(name: str, words: set[str], hidden: bool) -> int:
            up = stack.open[-1][1]
            if self.depth[up] >= DEEPEST:
                up = self.parent[up]
            tags.append(name)
            words_of_class.append(words)
            dark.append(dark[stack.open[-1][1]] or hidden)
            self.parent.append(up)
            self.depth.append(self.depth[up] + 1)
            return len(tags) - 1

        def flush() -> None:
            nonlocal linked
            if run:
                text = " ".join(entities.unescape("".join(run)).split())
                run.clear()
                if text and not dark[stack.open[-1][1]]:
                    node = add(TEXT, set(), False)
                    self.runs.append((node, text))
                    stats[node] = (len(text), min(linked, len(text)))
            linked = 0

        in_link = 0
        for m in tokens(source):
            token = m.group()
            name = m.group(3) if m.re is _TOKEN else None
            if name is None:
                if token[0] != "<" or token == "<":
                    run.append(token)
                    if in_link:
                        linked += len(token)
                elif m.group(1):
                    run.append(" ")
                continue
            name = name.lower()
            if name in INLINE:  # inline markup has no node: only links and breaks matter
                if name == "a":
                    in_link = 0 if m.group(2) else 1
                elif not m.group(2) and name in VOID and name == "br":
                    run.append(" ")
                continue
            if m.group(2):
                if stack.count[name]:
                    flush()
                    in_link = 0
                    stack.close(name)
                continue
            flush()
            in_link = 0
            if name in P_CLOSERS:
                stack.imply({"p"})
            if name == "tr":  # a row ends the open cell first
                stack.imply(SAME_CLOSERS["td"])
            if name in SAME_CLOSERS:
                stack.imply(SAME_CLOSERS[name])
            if name in VOID or name == "html":
                continue
            attrs = m.group(4)
            words = {w for a in _ATTR.findall(attrs) for w in _WORD.findall(" ".join(a).lower())} if "=" in attrs else set()
            node = add(name, words, name == "head" or bool(attrs and _HIDDEN.search(attrs)))
            if not attrs.endswith("/"):
                stack.push(name, node)
        flush()
        self.features = self._features(tags, words_of_class, stats)

    def _features(self, tags: list[str], classes: list[set], stats: dict[int, tuple[int, int]]) -> np.ndarray:
        n = len(tags)
        x = np.zeros((n, N_FEATURES))
        total, linked, blocks = np.zeros(n), np.zeros(n), np.zeros(n)
        for node, (chars, in_links) in stats.items():
            total[node], linked[node], blocks[node] = chars, in_links, 1
        for i in range(n - 1, 0, -1):  # children follow their parents
            p = self.parent[i]
            total[p] += total[i]
            linked[p] += linked[i]
            blocks[p] += blocks[i]
        for i, (tag, words) in enumerate(zip(tags, classes, strict=True)):
            if (t := _TAG_AT.get(tag)) is not None:
                x[i, t] = 1
            for w in words:
                if (g := _GROUP_AT.get(w)) is not None:
                    x[i, len(TAGS) + g] = 1
        base = len(TAGS) + len(GROUPS)
        texts = dict(self.runs)
        x[:, base] = 1
        x[:, base + 1] = np.log1p(total) / 6
        x[:, base + 2] = linked / np.maximum(total, 1)
        x[:, base + 3] = total / max(total[0], 1)
        x[:, base + 4] = np.log1p(total / np.maximum(blocks, 1)) / 6
        for node, text in texts.items():
            x[node, base + 5] = text[-1] in ".!?:;\"'”»)"
            x[node, base + 6] = text.count(",") + text.count(". ") > 0
            x[node, base + 7] = "©" in text or "(c)" in text
            x[node, base + 8] = len(text) < 25
        return x


class Forest:
    """Many pages' trees side by side, ordered by depth for level-wise messages."""

    def __init__(self, pages: list[Page]) -> None:
        shift = np.cumsum([0, *(len(p.parent) for p in pages)])
        self.x = np.concatenate([p.features for p in pages])
        self.parent = np.concatenate([np.where(np.array(p.parent) < 0, -1, np.array(p.parent) + s) for p, s in zip(pages, shift[:-1], strict=True)])
        depth = np.concatenate([np.array(p.depth) for p in pages])
        order = np.argsort(depth, kind="stable")
        self.levels = np.split(order, np.searchsorted(depth[order], np.arange(1, int(depth.max()) + 1)))
        self.kind = self.x[:, : len(TAGS)] @ np.array([_KIND.get(t, 0) for t in TAGS])
        self.kind = self.kind.astype(int)
        self.shift = shift

    def marginals(self, unary: np.ndarray, pair: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """unary (n): log potential of label 1; pair (kinds, parent label, child label) -> P(label 1), P(parent, child), log partition."""
        n = len(unary)
        up = np.zeros((n, 2))
        up[:, 1] = unary
        sent = np.zeros((n, 2))  # message of a node to its parent
        for nodes in self.levels[:0:-1]:
            joint = pair[self.kind[nodes]] + up[nodes][:, None, :]
            sent[nodes] = np.logaddexp(joint[:, :, 0], joint[:, :, 1])
            np.add.at(up, self.parent[nodes], sent[nodes])
        full = up.copy()
        both = np.zeros((n, 2, 2))
        log_z = float(np.logaddexp(up[self.levels[0], 0], up[self.levels[0], 1]).sum())
        for nodes in self.levels[1:]:
            p = self.parent[nodes]
            without = full[p] - sent[nodes]
            joint = pair[self.kind[nodes]] + up[nodes][:, None, :] + without[:, :, None]
            down = np.logaddexp(joint[:, 0, :], joint[:, 1, :])
            full[nodes] = down
            top = joint.max(axis=(1, 2), keepdims=True)
            e = np.exp(joint - top)
            both[nodes] = e / e.sum(axis=(1, 2), keepdims=True)
        prob = 1 / (1 + np.exp(np.clip(full[:, 0] - full[:, 1], -500, 500)))
        return prob, both, log_z


def fit(pages: list[Page], labels: list[np.ndarray], rounds: int = 300, penalty: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """Weights of the features and pair potentials: penalised maximum likelihood by gradient steps with adaptive sizes."""
    forest, y = Forest(pages), np.concatenate(labels).astype(int)
    w, pair = np.zeros(N_FEATURES), np.zeros((KINDS, 2, 2))
    child = np.concatenate(forest.levels[1:])
    seen = np.zeros((KINDS, 2, 2))
    np.add.at(seen, (forest.kind[child], y[forest.parent[child]], y[child]), 1)
    m1, m2, v1, v2 = np.zeros_like(w), np.zeros_like(pair), np.zeros_like(w), np.zeros_like(pair)
    for t in range(1, rounds + 1):
        prob, both, _ = forest.marginals(forest.x @ w, pair)
        g1 = (forest.x.T @ (y - prob) - penalty * w) / len(pages)
        expected = np.stack([both[child[forest.kind[child] == k]].sum(axis=0) for k in range(KINDS)])
        g2 = (seen - expected - penalty * pair) / len(pages)
        m1, m2 = 0.9 * m1 + 0.1 * g1, 0.9 * m2 + 0.1 * g2
        v1, v2 = 0.99 * v1 + 0.01 * g1 * g1, 0.99 * v2 + 0.01 * g2 * g2
        rate = 0.15 / (1 - 0.9**t)
        w = w + rate * m1 / (np.sqrt(v1 / (1 - 0.99**t)) + 1e-8)
        pair = pair + rate * m2 / (np.sqrt(v2 / (1 - 0.99**t)) + 1e-8)
    return w, pair


_SYLLABLES = "ba ren to mi la sho ver ka dul en or ist ga pe lo run ta ve no ri".split()


def labelled_page(rng: random.Random) -> tuple[str, list[bool]]:
    """A page of a random layout; the label of each of its text runs in page order."""
    out, truth = [], []

    def words(a: int, b: int) -> str:
        n = rng.randint(a, b)
        ws = ["".join(rng.choices(_SYLLABLES, k=rng.randint(1, 3))) for _ in range(n)]
        if rng.random() < 0.1:
            ws = [x + rng.choice(["###", "%%%", "&amp;&amp;", "!!"]) for x in ws]
        if rng.random() < 0.05:
            ws = [x.upper() for x in ws]
        return " ".join(ws)

    def sentence(a: int = 1, b: int = 40) -> str:
        """One sentence or several, with commas or without, wherever text stands."""
        parts = []
        for _ in range(rng.choice([1, 1, 2, 3])):
            ws = words(a, b).split()
            ws = [w + "," if rng.random() < 0.08 else w for w in ws]
            parts.append(" ".join(ws).capitalize() + rng.choice([".", ".", ".", ".", "?", ""]))
        return " ".join(parts)

    def say(text: str, good: bool, tag: str = "", attrs: str = "", closed: bool = True) -> None:
        out.append(f"<{tag}{attrs}>{text}" + (f"</{tag}>" if closed else "") if tag else text)
        truth.append(good)

    def named(*names: str) -> str:
        return rng.choice(["", *(f' class="{n}"' for n in names), *(f' id="{n}"' for n in names)])

    def surely(*names: str) -> str:
        return f' {rng.choice(["class", "id"])}="{rng.choice(names)}"'

    def links(n: int, tag: str = "li") -> None:
        for _ in range(n):
            say(f'<a href="/{words(1, 1)}">{words(1, 3)}</a>', False, tag)

    def menu() -> None:
        tag = rng.choice(["nav", "nav", "div", "ul"])
        out.append(f"<{tag}{surely('menu', 'nav', 'navbar', 'navigation', 'breadcrumb') if tag != 'nav' else named('menu', 'top')}>")
        if tag != "ul":
            out.append("<ul>")
        links(rng.randint(2, 8))
        out.append(f"</ul></{tag}>" if tag != "ul" else "</ul>")

    def box(names: list[str], tags: list[str], good: bool = False, parts: tuple[int, int] = (1, 3)) -> None:
        tag = rng.choice(tags)
        out.append(f"<{tag}{surely(*names) if tag in ('div', 'section', 'p') else named(*names)}>")
        if rng.random() < 0.4:
            say(sentence(1, 25), good)
        else:
            for _ in range(rng.randint(*parts)):
                say(sentence(1, 30), good, rng.choice(["p", "p", "h3", "div"]))
        if rng.random() < 0.3:
            out.append("<ul>")
            links(rng.randint(2, 5))
            out.append("</ul>")
        out.append(f"</{tag}>")

    def form() -> None:
        out.append(f"<form{named('search', 'newsletter', 'signup', 'login')}>")
        say(sentence(1, 12), False, rng.choice(["label", "p", "div"]))
        out.append('<input type="text"><button>Go</button></form>')

    def comments() -> None:
        tag = rng.choice(["section", "div", "ol", "aside"])
        out.append(f"<{tag}{surely('comments', 'comment-list', 'discussion', 'responses')}>")
        for _ in range(rng.randint(1, 5)):
            out.append(f"<div{named('comment', 'reply')}>" if tag != "ol" else "<li>")
            if rng.random() < 0.5:
                say(words(1, 2), False, rng.choice(["b", "h4", "p"]) if rng.random() < 0.5 else "p")
            for _ in range(rng.randint(1, 3)):
                say(sentence(2, 60), False, "p")
            out.append("</div>" if tag != "ol" else "</li>")
        out.append(f"</{tag}>")

    def junk() -> None:
        rng.choice(
            [
                lambda: box(["ad", "ads", "advert", "banner", "sponsor", "promo"], ["div", "div", "aside", "section"]),
                lambda: box(["cookie", "consent", "notice", "alert", "popup"], ["div", "section", "p"], parts=(1, 1)),
                lambda: box(["share", "social", "subscribe", "newsletter", "related"], ["div", "section", "aside"]),
                form,
                lambda: box(["sidebar", "side", "widget", "related"], ["aside", "div", "section"]),
            ]
        )()

    def body_of_article() -> None:
        for _ in range(rng.randint(1, 12)):
            kind = rng.random()
            if kind < 0.72:
                text = sentence(1, rng.choice([6, 30, 120]))
                if rng.random() < 0.2:
                    text = f"<b>{text}<br>" if rng.random() < 0.5 else f'{text} <a href="#">{words(1, 3)}</a> {sentence(1, 9)}'
                say(text, True, "p", closed=rng.random() < 0.8)
            elif kind < 0.8:
                say(words(1, 9), True, rng.choice(["h2", "h3"]))
            elif kind < 0.88:
                tag = rng.choice(["ul", "ol"])
                out.append(f"<{tag}>")
                for _ in range(rng.randint(2, 5)):
                    say(sentence(1, 15), True, "li", closed=rng.random() < 0.8)
                out.append(f"</{tag}>")
            elif kind < 0.92:
                say(sentence(4, 40), True, rng.choice(["blockquote", "pre", "div"]))
            elif kind < 0.95:
                out.append("<table><tr>")
                for _ in range(rng.randint(2, 4)):
                    say(words(1, 4), True, "td")
                out.append("</tr></table>")
            else:
                junk()

    out.append('<!DOCTYPE html><html lang="en"><head><meta charset="utf-8"><title>t</title><style>p{}</style><script>var a="</p>";</script></head><body>')
    if rng.random() < 0.5:
        out.append(f"<header{named('header', 'masthead', 'site-header')}>")
        say(words(1, 4), False, rng.choice(["h1", "div", "p", "h2"]))
        if rng.random() < 0.5:
            menu()
        out.append("</header>")
    for _ in range(rng.randint(0, 2)):
        menu()
    for _ in range(rng.randint(0, 2)):
        junk()
    shell = rng.choice(["article", "article", "article", "main", "main+article", "div", "div+div"])
    tags = []
    for part in shell.split("+"):
        tags.append(part)
        out.append(f"<{part}{surely('content', 'post', 'entry', 'article', 'story', 'main-content', 'article-body') if part == 'div' else named('content', 'post', 'article', 'entry')}>")
    if rng.random() < 0.8:
        wrap = rng.random() < 0.2 and shell != "div"
        out.append("<header>" if wrap else "")
        say(words(1, 14), True, rng.choice(["h1", "h1", "h2"]))
        out.append("</header>" if wrap else "")
    body_of_article()
    for _ in range(rng.randint(0, 1)):
        junk()
    inside = rng.random() < 0.3
    if inside and rng.random() < 0.7:
        comments()
    out.extend(f"</{t}>" for t in reversed(tags))
    if not inside and rng.random() < 0.5:
        comments()
    for _ in range(rng.randint(0, 2)):
        junk()
    if rng.random() < 0.9:
        tag = rng.choice(["footer", "footer", "div"])
        out.append(f"<{tag}{surely('footer', 'copyright', 'legal') if tag == 'div' else named('footer')}>")
        say(f"&copy; {words(1, 3)} &middot; {sentence(1, 25)}", False, rng.choice(["", "p"]))
        if rng.random() < 0.4:
            out.append("<ul>")
            links(rng.randint(2, 5))
            out.append("</ul>")
        out.append(f"</{tag}>")
    out.append("</body></html>")
    return "".join(out), truth


def node_labels(page: Page, truth: list[bool]) -> np.ndarray:
    """Runs have their own labels; an element has label 1 if it holds any content."""
    y = np.zeros(len(page.parent))
    mass = np.zeros((len(page.parent), 2))
    for (node, text), good in zip(page.runs, truth, strict=True):
        y[node] = good
        mass[node, int(good)] = len(text)
    for i in range(len(page.parent) - 1, 0, -1):
        mass[page.parent[i]] += mass[i]
    inner = np.ones(len(y), dtype=bool)
    inner[[n for n, _ in page.runs]] = False
    y[inner] = mass[inner, 1] > 0
    return y


@functools.cache
def trained(n_pages: int = 400, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Weights from n_pages generated pages; a second or two, once in a process."""
    rng = random.Random(seed)
    pages, labels = [], []
    while len(pages) < n_pages:
        source, truth = labelled_page(rng)
        page = Page(source)
        if len(page.runs) == len(truth):
            pages.append(page)
            labels.append(node_labels(page, truth))
    return fit(pages, labels)


def main_texts(sources: list[str], weights: tuple[np.ndarray, np.ndarray]) -> list[str]:
    """The runs whose marginal for content is over a half, in page order."""
    pages = [Page(s) for s in sources]
    if not pages:
        return []
    forest = Forest(pages)
    prob, _, _ = forest.marginals(forest.x @ weights[0], weights[1])
    return ["\n".join(text for node, text in p.runs if prob[s + node] > 0.5) for p, s in zip(pages, forest.shift[:-1], strict=True)]
