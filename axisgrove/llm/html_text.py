"""Main text of web pages by a graphical model over the DOM tree.

Elements are binary variables (part of the main text or not). Each has a unary potential
from its tag, its class and id words and the text below it; each parent-child edge has a
potential by kind of child. The model is a tree, so one upward and one downward sweep of
sum-product messages gives exact marginals; the same sweeps give the gradient for training
by maximum likelihood on labelled pages. All pages of a batch are swept together, level by level.
"""

from __future__ import annotations

import random
import re
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from axisgrove.llm.common import keeping, table

# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noframes xmp svg math".split())
#: Never shown as running text, whatever stands in it.
DROPPED = RAW | frozenset("head select option button datalist object canvas audio video map dialog".split())
BLOCK = frozenset(
    "html body div section article main nav header footer aside form fieldset ul ol li dl dt dd p h1 h2 h3 h4 h5 h6 table caption thead tbody tfoot tr td th blockquote pre figure figcaption address hr details summary center hgroup menu search head".split()
)
#: Elements that an opening tag of the key ends, where one is open above the nearest bound.
ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "body": ("head",)}
BOUNDS = frozenset("ul ol dl table menu".split())
TAGS = ["body", "div", "section", "article", "main", "nav", "header", "footer", "aside", "form", "list", "li", "p", "heading", "table", "cell", "quote", "figure", "inline", "other"]
GROUP = {"html": "body", "ul": "list", "ol": "list", "dl": "list", "menu": "list", "dt": "li", "dd": "li", "fieldset": "form", "tr": "table", "thead": "table", "tbody": "table", "td": "cell", "th": "cell", "blockquote": "quote", "pre": "quote", "figcaption": "figure", "search": "form"} | {f"h{i}": "heading" for i in range(1, 7)}
#: Words in class, id and role that hint at a role of the element.
HINTS = {
    "navigation": "nav navbar navigation menu menubar breadcrumb breadcrumbs pagination pager toc skip tabs topbar",
    "frame": "header masthead banner footer foot bottom copyright legal colophon contentinfo imprint",
    "side": "sidebar side aside widget widgets complementary rail related recommended recommendations more popular trending also teaser teasers archive tags categories",
    "advert": "ad ads adv advert advertisement advertising sponsor sponsored promo promotion promoted banner commercial dfp adsense outbrain taboola",
    "notice": "cookie cookies consent notice notices gdpr alert popup modal overlay newsletter subscribe subscription signup paywall warning message toast hint info",
    "form": "form login search contact register input captcha poll survey",
    "comment": "comment comments commentlist reply replies respond disqus discussion thread reactions reviews feedback guestbook",
    "share": "share sharing social byline meta author tools print bookmark rating vote follow like likes",
    "main": "article content post entry story main body text maincontent articlebody prose page copy",
    "hidden": "hidden invisible offscreen sr screenreader none",
}
_HINT = {w: k for k, words in HINTS.items() for w in words.split()}
_KINDS = list(HINTS)
#: Inline formatting that is no variable of the model unless it carries a class, id or role.
_PLAIN_INLINE = frozenset("a abbr b bdi bdo big br cite code del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())

_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)((?>[^>\"']|\"[^\"]*\"|'[^']*')*+)>?")
_ATTRIBUTE = re.compile(r"""(class|id|role|style|aria-hidden|hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?(?=[\s/]|$)""", re.I)
_WORD = re.compile(r"[a-z]+")
_SENTENCE = re.compile(r"[.!?;:,](?:\s|$)")
_BREAK = re.compile(r"</(?=[a-zA-Z])|<(?=[a-zA-Z!?/])")


class Page:
    """Elements of a page in document order, and its text pieces.

    ``pieces``: (element, text, block number, link), decoded but with white space as it stands.
    """

    def __init__(self, html: str | None):
        self.tag, self.hints, self.parent, self.depth = ["body"], [frozenset()], [-1], [0]
        self.pieces: list[tuple[int, str, int, bool]] = []
        self._parse(html or "")

    def _parse(self, html: str) -> None:
        stack: list[tuple[str, int]] = [("#root", 0)]  # tag, element
        open_: dict[str, int] = {}
        dropped = links = block = at = 0
        end = len(html)

        def close(upto: int) -> None:
            nonlocal dropped, links, block
            while len(stack) > upto:
                name, _ = stack.pop()
                open_[name] -= 1
                dropped -= name in DROPPED
                links -= name == "a"
                block += name in BLOCK

        while at < end:
            found = _BREAK.search(html, at)
            stop = found.start() if found else end
            if stop > at and not dropped:
                self.pieces.append((stack[-1][1], unescape(html[at:stop]), block, links > 0))
            if not found:
                break
            at = stop
            if html.startswith("<!--", at):
                stop = html.find("-->", at + 4)
                at = end if stop < 0 else stop + 3
                continue
            tag = _TAG.match(html, at) if html[at + 1] not in "!?" else None
            if tag is None:
                stop = html.find(">", at)
                at = end if stop < 0 else stop + 1
                continue
            at = tag.end()
            name = tag[2].lower()
            if tag[1]:
                if open_.get(name):
                    k = len(stack) - 1
                    while stack[k][0] != name:
                        k -= 1
                    close(k)
                elif name == "p":
                    block += 1
                continue
            if name in BLOCK and open_.get("p"):
                k = len(stack) - 1
                while stack[k][0] != "p":
                    k -= 1
                close(k)
            for other in ENDS.get(name, ()):
                if open_.get(other):
                    k = len(stack) - 1
                    while stack[k][0] != other and stack[k][0] not in BOUNDS:
                        k -= 1
                    if stack[k][0] == other:
                        close(k)
            block += name in BLOCK
            if name == "br" and not dropped:
                self.pieces.append((stack[-1][1], " ", block, False))
            if name in VOID or tag[3].endswith("/") and name not in BLOCK:
                continue
            attributes = tag[3]
            hints = self._hints(attributes) if attributes and not attributes.isspace() else frozenset()
            if name in RAW:
                close_tag = re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I).search(html, at)
                at = end if close_tag is None else close_tag.start()
                if close_tag is not None:
                    stop = html.find(">", at)
                    at = end if stop < 0 else stop + 1
                continue
            element = stack[-1][1]
            if name == "body" or name == "html":
                self.hints[0] = self.hints[0] | hints
                element = 0
            elif name not in _PLAIN_INLINE or hints:
                element = len(self.tag)
                self.tag.append(name)
                self.hints.append(hints)
                self.parent.append(stack[-1][1])
                self.depth.append(self.depth[stack[-1][1]] + 1)
            stack.append((name, element))
            open_[name] = open_.get(name, 0) + 1
            dropped += name in DROPPED
            links += name == "a"

    @staticmethod
    def _hints(attributes: str) -> frozenset:
        found = set()
        for m in _ATTRIBUTE.finditer(attributes):
            key, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
            if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
                found.add("hidden")
            elif key in ("class", "id", "role"):
                found |= {_HINT[w] for w in _WORD.findall(value) if w in _HINT}
        return frozenset(found)

    def blocks(self, shown) -> list[tuple[str, int]]:
        """Texts of the blocks, from pieces whose element is in ``shown``, and one element of each."""
        out: list[tuple[str, int]] = []
        held: list[str] = []
        last, who = None, 0
        for element, text, block, _ in self.pieces:
            if not shown[element]:
                continue
            if block != last and held:
                out.append((" ".join("".join(held).split()), who))
                held = []
            last, who = block, element
            held.append(text)
        if held:
            out.append((" ".join("".join(held).split()), who))
        return [x for x in out if x[0]]


FEATURES = [*(f"tag:{t}" for t in TAGS), *(f"hint:{k}" for k in _KINDS), "own", "below", "links", "sentences", "words_a_block", "first", "last", "paragraphs", "one"]
_TAG_AT = {t: i for i, t in enumerate(TAGS)}
_HINT_AT = {k: len(TAGS) + i for i, k in enumerate(_KINDS)}
#: Kinds of edges, by the child: plain, with an unwanted hint or tag, with a main hint or tag.
_EDGES = 3
_UNWANTED_TAGS, _MAIN_TAGS = frozenset("nav header footer aside form".split()), frozenset("article main".split())


def page_features(page: Page) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of the elements and the kinds of the edges to their parents."""
    n = len(page.tag)
    own, linked, marks, blocks, where = [0.0] * n, [0.0] * n, [0.0] * n, [0.0] * n, [-1.0] * n
    total, last = 0, None
    for element, text, block, link in page.pieces:
        size = len(text)
        if text.isspace() or not size:
            continue
        own[element] += size
        linked[element] += size * link
        marks[element] += len(_SENTENCE.findall(text))
        blocks[element] += block != last
        last = block
        if where[element] < 0:
            where[element] = total
        total += size
    below, below_linked, below_marks, below_blocks, paragraphs = own[:], linked[:], marks[:], blocks[:], [0.0] * n
    for i in range(n - 1, 0, -1):
        p = page.parent[i]
        below[p] += below[i]
        below_linked[p] += below_linked[i]
        below_marks[p] += below_marks[i]
        below_blocks[p] += below_blocks[i]
        paragraphs[p] += paragraphs[i] + (page.tag[i] == "p")
        if where[i] >= 0 and (where[p] < 0 or where[i] < where[p]):
            where[p] = where[i]
    x = np.zeros((n, len(FEATURES)), dtype=np.float32)
    edge = np.zeros(n, dtype=np.int64)
    k = len(TAGS) + len(_KINDS)
    for i in range(n):
        tag = page.tag[i]
        group = GROUP.get(tag, tag)
        x[i, _TAG_AT.get(group, _TAG_AT["inline" if tag in _PLAIN_INLINE else "other"])] = 1
        for h in page.hints[i]:
            x[i, _HINT_AT[h]] = 1
        at = where[i] / total if total and where[i] >= 0 else 0.5
        x[i, k:] = (min(own[i], 2000) ** 0.5 / 20, min(below[i], 5000) ** 0.5 / 30, below_linked[i] / below[i] if below[i] else 0, min(1, 20 * below_marks[i] / below[i]) if below[i] else 0, min(below[i] / max(1, below_blocks[i]), 600) / 300, at < 0.08, at > 0.9, min(paragraphs[i], 5) / 5, 1)
        if tag in _UNWANTED_TAGS or page.hints[i] - {"main"}:
            edge[i] = 1
        elif tag in _MAIN_TAGS or "main" in page.hints[i]:
            edge[i] = 2
    return x, edge


class Forest:
    """Pages laid side by side, with their elements listed by depth."""

    def __init__(self, pages: list[Page]):
        parts = [page_features(p) for p in pages]
        self.first = np.concatenate([[0], np.cumsum([len(p.tag) for p in pages])]).astype(np.int64)
        self.x = np.concatenate([x for x, _ in parts]) if parts else np.zeros((0, len(FEATURES)), np.float32)
        self.edge = np.concatenate([e for _, e in parts]) if parts else np.zeros(0, np.int64)
        self.parent = np.concatenate([np.where(np.array(p.parent) < 0, -1, np.array(p.parent) + f) for p, f in zip(pages, self.first, strict=False)]) if parts else np.zeros(0, np.int64)
        depth = np.concatenate([np.array(p.depth) for p in pages]) if parts else np.zeros(0, np.int64)
        order = np.argsort(depth, kind="stable")
        self.levels = np.split(order, np.cumsum(np.bincount(depth))[:-1]) if parts else []


class TreeModel:
    def __init__(self):
        self.unary = np.zeros(len(FEATURES))
        #: By kind of edge, label of the parent, label of the child.
        self.pair = np.zeros((_EDGES, 2, 2))

    def marginals(self, f: Forest) -> tuple[np.ndarray, np.ndarray]:
        """P(element is main text), and P(parent label, child label) of the edges."""
        n = len(f.edge)
        up = np.zeros((n, 2))
        up[:, 1] = f.x @ self.unary
        message = np.zeros((n, 2))
        for nodes in f.levels[:0:-1]:  # children to parents
            message[nodes] = np.logaddexp.reduce(self.pair[f.edge[nodes]] + up[nodes][:, None, :], axis=2)
            np.add.at(up, f.parent[nodes], message[nodes])
        down = np.zeros((n, 2))
        joint = np.zeros((n, 2, 2))
        for nodes in f.levels[1:]:  # parents to children
            p = f.parent[nodes]
            rest = up[p] + down[p] - message[nodes]
            scored = self.pair[f.edge[nodes]] + rest[:, :, None]
            down[nodes] = np.logaddexp.reduce(scored, axis=1)
            scored = scored + up[nodes][:, None, :]
            joint[nodes] = np.exp(scored - np.logaddexp.reduce(scored.reshape(len(nodes), 4), axis=1)[:, None, None])
        belief = up + down
        return np.exp(belief[:, 1] - np.logaddexp(belief[:, 0], belief[:, 1])), joint

    def fit(self, pages: list[Page], labels: list[np.ndarray], steps: int = 160, rate: float = 0.7, decay: float = 1e-3) -> TreeModel:
        """Gradient ascent (with momentum) on the likelihood of the labels."""
        f, y = Forest(pages), np.concatenate(labels).astype(np.int64)
        inner = np.flatnonzero(f.parent >= 0)
        real = np.zeros((len(y), 2, 2))
        real[inner, y[f.parent[inner]], y[inner]] = 1
        speed_u, speed_p = np.zeros_like(self.unary), np.zeros_like(self.pair)
        for _ in range(steps):
            p, joint = self.marginals(f)
            grad_u = f.x.T @ (y - p) / len(y) - decay * self.unary
            grad_p = np.stack([(real - joint)[inner][f.edge[inner] == e].sum(axis=0) for e in range(_EDGES)]) / len(y) - decay * self.pair
            speed_u, speed_p = 0.9 * speed_u + rate * grad_u, 0.9 * speed_p + rate * grad_p
            self.unary, self.pair = self.unary + speed_u, self.pair + speed_p
        return self


def main_blocks(model: TreeModel, pages: list[Page]) -> list[list[str]]:
    """The blocks of main text of each page."""
    p, _ = model.marginals(f := Forest(pages))
    return [[t for t, _ in page.blocks(p[a:b] > 0.5)] for page, a, b in zip(pages, f.first, f.first[1:], strict=False)]


def labelled_pages(n: int = 320, seed: int = 3) -> tuple[list[Page], list[np.ndarray]]:
    """Pages made by rule, with the label of every element: main text if most text below it is."""
    rng = random.Random(seed)
    words = "the of and der die las que on that river stone light paper window signal engine garden market winter north letter music bridge copper animal".split()

    def sentence(a: int, b: int) -> str:
        return " ".join(rng.choice(words) for _ in range(rng.randint(a, b))).capitalize() + rng.choice("..!?")

    def prose(sentences: int) -> str:
        return " ".join(sentence(4, 16) for _ in range(rng.randint(1, sentences)))

    good = lambda s: f"\x01{s}"  # noqa: E731  marks text as main

    def el(tag: str, inner: str, names: str = "") -> str:
        attr = f' {rng.choice(["class", "class", "id"])}="{rng.choice(names.split())}"' if names else ""
        return f"<{tag}{attr}>{inner}</{tag}>"

    def links(k: int) -> str:
        return el("ul", "".join(el("li", f'<a href="/x">{sentence(1, 3)}</a>') for _ in range(rng.randint(2, k))))

    def extras() -> list[str]:
        return [
            el("nav", links(8)),
            el("div", links(8), "menu nav navbar breadcrumb main-menu"),
            el("header", rng.choice([el("h1", sentence(1, 4)), el("div", sentence(2, 5), "logo banner"), el("p", sentence(2, 8))])),
            el("div", el("h2", sentence(1, 3)) + links(5), "header masthead top-banner"),
            el("aside", el("h3", sentence(1, 3)) + rng.choice([links(5), el("p", prose(2))])),
            el("div", el("h3", sentence(1, 3)) + rng.choice([links(5), el("p", prose(3))]), "sidebar side widget related recommended"),
            el("div", prose(2), "ad ads advert ad-box sponsored promo banner-ad"),
            el("section", el("p", prose(2)), "sponsored advertisement promo newsletter"),
            el("div", el("p", prose(2)) + "<button>ok</button>", "cookie-notice notice consent-banner alert cookie popup"),
            el("div", rng.choice([prose(1), el("p", prose(2))]), "notice message warning newsletter subscribe paywall"),
            el("form", el("label", sentence(1, 3)) + "<input name=q>" + rng.choice(["", el("p", prose(2)), "<textarea>x</textarea><button>go</button>"])),
            el("div", el("p", prose(1)), "login search-form contact-form signup"),
            el("div", sentence(1, 4) + links(4), "share social tags meta"),
        ]

    def comments() -> str:
        one = lambda: rng.choice([el("div", rng.choice([el("p", prose(4)), el("b", sentence(1, 2)) + prose(3), el("h4", sentence(1, 2)) + el("p", prose(5))]), "comment reply comment-body"), el("li", rng.choice([el("p", prose(3)), prose(3)])), el("article", el("p", prose(3)), "comment")])
        many = "".join(one() for _ in range(rng.randint(1, 6)))
        head = el(rng.choice(["h2", "h3"]), sentence(1, 2)) if rng.random() < 0.7 else ""
        return el(rng.choice(["div", "section", "ol", "aside"]), head + many, "comments commentlist discussion comment-section disqus responses-comments")

    def body() -> str:
        parts = [el("h1", good(sentence(2, 9)))] if rng.random() < 0.8 else []
        for _ in range(rng.choice([1, 1, 1, 2, 2, 3, 4, 5, 7, 9])):
            kind = rng.random()
            if kind < 0.72:
                text = prose(rng.choice([1, 2, 7, 7]))
                if rng.random() < 0.15:
                    text = "<b>" + text + "<br>"
                if rng.random() < 0.3:
                    text = text + f' <a href="/y">{sentence(1, 4)}</a> ' + sentence(2, 9)
                parts.append(f"<p>{good(text)}" + rng.choice(["</p>", "</p>", ""]))
            elif kind < 0.8:
                parts.append(el("h2", good(sentence(1, 6))))
            elif kind < 0.86:
                parts.append(el(rng.choice(["ul", "ol"]), "".join(el("li", good(sentence(2, 12))) for _ in range(rng.randint(2, 5)))))
            elif kind < 0.9:
                parts.append(el("blockquote", el("p", good(prose(3)))))
            elif kind < 0.93:
                parts.append(el("pre", good(prose(2))))
            elif kind < 0.96:
                parts.append(el("table", el("tr", el("td", good(sentence(1, 4))) + el("td", good(sentence(1, 4))))))
            else:
                parts.append(el("div", good(prose(5))))
        for _ in range(rng.choice([0, 0, 0, 1, 2])):
            parts.insert(rng.randint(1, len(parts)), rng.choice(extras()[4:]))
        if rng.random() < 0.25:
            parts.append(comments())
        return "".join(parts)

    pages, labels = [], []
    for _ in range(n):
        main = body()
        style = rng.random()
        if style < 0.4:
            main = el("article", main, rng.choice(["", "", "post entry story"]))
        elif style < 0.6:
            main = el("main", rng.choice([main, el("article", main)]))
        elif style < 0.85:
            main = el(rng.choice(["div", "section"]), main, "content main article-body post entry-content story text")
        elif style < 0.93:
            main = el("div", main)
        before = "".join(rng.sample(extras()[:5] + extras()[6:10], rng.randint(0, 4)))
        after = "".join(rng.sample(extras()[4:], rng.randint(0, 3))) + (comments() if rng.random() < 0.4 else "")
        foot = rng.choice([el("footer", "&copy; " + prose(2)), el("footer", el("p", prose(2)) + links(4)), el("div", prose(2), "footer copyright legal"), ""])
        inner = before + main + after + foot
        if rng.random() < 0.3:
            inner = el("div", inner, rng.choice(["", "wrapper container page"]))
        page = Page(f"<!DOCTYPE html><html><head><title>{sentence(2, 5)}</title></head><body>{inner}</body></html>")
        right, total = np.zeros(len(page.tag)), np.full(len(page.tag), 1e-9)
        marked: dict[tuple[int, int], bool] = {}
        for element, text, block, _ in page.pieces:
            key = (element, block)
            marked[key] = marked.get(key, False) or "\x01" in text
            right[element] += len(text) * marked[key]
            total[element] += len(text)
        page.pieces = [(e, t.replace("\x01", ""), b, k) for e, t, b, k in page.pieces]
        for i in range(len(page.tag) - 1, 0, -1):
            right[page.parent[i]] += right[i]
            total[page.parent[i]] += total[i]
        pages.append(page)
        labels.append(right / total > 0.5)
    return pages, labels


@lru_cache(maxsize=1)
def default_model() -> TreeModel:
    return TreeModel().fit(*labelled_pages())


@keeping
def extract(pages: DataFrame, keep: tuple[str, ...] = ("page_id", "url"), html: str = "html", out: str = "main_text", model: TreeModel | None = None) -> DataFrame:
    """``keep`` and the main text: white space inside a block is one space, blocks are joined by newlines.

    A null or empty page has an empty text. Repeated rows are treated alike, an empty table gives no
    rows, and a page is never cut however long it is.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    model = model or default_model()
    fields = pages.select(*keep, html)
    schema = ", ".join(f"`{c}` {fields.schema[c].dataType.simpleString()}" for c in keep) + f", `{out}` string"

    def work(batches):
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                texts = ["\n".join(b) for b in main_blocks(model, [Page(h) for h in part.column(html).to_pylist()])]
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(texts, pa.string())], names=[*keep, out])

    return fields.mapInArrow(work, schema)


def op4_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    found = extract(table(spark, sf_dir, "pages"), out="text")
    return found.selectExpr("page_id", "url", "text", "cast(length(text) as bigint) as n_chars")
