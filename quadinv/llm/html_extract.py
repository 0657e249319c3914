"""Main text of web pages by a tree-structured graphical model over the DOM.

Every block element of a page is a node with a hidden label, main text or not. A node's features (tag, names in class, id and
role; and shape: text, links, sentences, place in the page, what lies beside it) give its own potential, and a potential for each
pair of parent and child ties the labels along the tree. Both are learned from labelled pages. Messages pass from the
leaves to the root and back (sum-product); where a node's marginal of main text is over one half, its own text is taken.

Text: character references are decoded, white space inside a block becomes one space, blocks are trimmed and joined by one
space in page order. Inline elements don't part words; a line break does. A null or empty page, and one without main text,
gives the empty text. Tags left open, stray end tags and unclosed comments are tolerated, in time that follows the page's length; text outside of any element belongs
to the body. Repeated pages give the same text.
"""

from __future__ import annotations

import html
import math
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import extended, table, with_columns
from .html_training import labelled_pages

#: Labelled pages that the model learns from.
TRAINING_PAGES = 2000
TURNS = 16

# Element names of HTML by how they are read.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr keygen frame".split())
SKIPPED = frozenset("script style noscript template svg iframe textarea select object canvas math title audio video datalist".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark output q rp rt ruby s samp small span strike strong sub sup time tt u var nobr wbr img picture input progress meter".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl dd dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section summary table ul li".split())
#: An element of the first kind ends an open one of the second, unless one of the third lies between.
ENDS = {
    "li": (frozenset(["li"]), frozenset(["ul", "ol", "menu"])),
    "dt": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "dd": (frozenset(["dt", "dd"]), frozenset(["dl"])),
    "tr": (frozenset(["tr"]), frozenset(["table"])),
    "td": (frozenset(["td", "th"]), frozenset(["tr", "table"])),
    "th": (frozenset(["td", "th"]), frozenset(["tr", "table"])),
    "option": (frozenset(["option"]), frozenset(["datalist"])),
    "body": (frozenset(["head"]), frozenset(["body"])),
}
BARRIER = frozenset("table td th button object".split())

COMMENT = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)", re.S)
# Possessive throughout: what has been taken isn't tried again, so that a tag costs no more than its length.
TAG = re.compile(r"""<(/?)([a-zA-Z][^\s/>]*+)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>""")
LOOSE = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>")
ATTRIBUTE = re.compile(r"""(?<![\w-])(class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+)""", re.I)
#: In training pages only: the mark of a labelled element. Pages to extract from are never searched for it.
LABEL = re.compile(r'data-y="([01])"')
NAME_PART = re.compile(r"[a-z]+|[A-Z][a-z]*")
SENTENCE = re.compile(r"""[.!?。؟]["'”)]?(?:\s|$)""")
#: Elements that name a part of the page.
PARTS = frozenset("article main nav header footer aside form section dialog menu table".split())


@lru_cache(maxsize=20_000)
def _names(attributes: str) -> tuple[str, ...]:
    """Lower-case words of class, id and role, whole names among them."""
    found = set()
    for key, value in ATTRIBUTE.findall(attributes):
        for name in value.strip("\"'").split():
            found.add(name.lower())
            found.update(p.lower() for p in NAME_PART.findall(name))
    return tuple(sorted(found))


class Open:
    """The open elements of a page, each with the node that its text belongs to, and where each name lies among them."""

    def __init__(self):
        self.tags, self.nodes, self.at, self.blocks, self.links = ["html"], [0], {}, [0], 0

    def push(self, tag: str, node: int) -> None:
        self.at.setdefault(tag, []).append(len(self.tags))
        if tag not in INLINE:
            self.blocks.append(len(self.tags))
        self.links += tag == "a"
        self.tags.append(tag)
        self.nodes.append(node)

    def last(self, tags) -> int:
        return max((self.at[t][-1] for t in tags if self.at.get(t)), default=0)

    def cut(self, k: int) -> None:
        """Close the k-th element and all in it."""
        while len(self.tags) > k:
            tag = self.tags.pop()
            self.nodes.pop()
            self.at[tag].pop()
            if tag not in INLINE:
                self.blocks.pop()
            self.links -= tag == "a"

    def close(self, ended: frozenset[str], kept: frozenset[str]) -> None:
        """End the innermost open element among ended, and what is open in it, unless one of kept lies between."""
        k = self.last(ended)
        if k and k >= self.last(kept):
            self.cut(k)


class Dom:
    """Block elements of a page in page order, with their runs of text. Reading takes time in proportion to the page.

    labelled: also read the labels of a training page.
    """

    def __init__(self, page: str, labelled: bool = False):
        self.tag, self.parent, self.names, self.label = ["html"], [-1], [()], [None]
        self.text: list[tuple[int, list[str]]] = []  # (node, pieces) of each run between block boundaries
        self.own, self.linked, self.stops, self.links, self.start, self.read = [0], [0], [0], [0], [0], 0
        self.labelled = labelled
        self._read(page)

    def _node(self, tag: str, parent: int, attributes: str) -> int:
        self.tag.append(tag)
        self.parent.append(parent)
        self.names.append(_names(attributes) if attributes else ())
        mark = LABEL.search(attributes) if self.labelled else None
        self.label.append(int(mark[1]) if mark else None)
        for count in (self.own, self.linked, self.stops, self.links):
            count.append(0)
        self.start.append(self.read)
        return len(self.tag) - 1

    def _text(self, raw: str, node: int, run: list[str], linked: bool) -> None:
        if "&" in raw:
            raw = html.unescape(raw)
        run.append(raw)
        size = len(raw.strip())
        self.own[node] += size
        self.read += size
        if linked:
            self.linked[node] += size
        elif size:
            self.stops[node] += len(SENTENCE.findall(raw))

    def _read(self, page: str) -> None:
        stack, at, run, length = Open(), 0, None, len(page)
        last = page.rfind(">")
        while at < length:
            begin = page.find("<", at)
            m = None
            while 0 <= begin:
                m = COMMENT.match(page, begin) if page[begin + 1 : begin + 2] in ("!", "?") else (TAG.match(page, begin) or LOOSE.match(page, begin)) if begin < last else None
                if m:
                    break
                begin = page.find("<", begin + 1) if begin < last else page.find("<!", begin + 1)
            end = begin if m else length
            if end > at:
                if run is None:
                    run = []
                    self.text.append((stack.nodes[-1], run))
                self._text(page[at:end], stack.nodes[-1], run, stack.links > 0)
            if not m:
                break
            at = m.end()
            if m.re is COMMENT:
                continue
            closing, tag, attributes = m[1], m[2].lower(), m[3]
            if closing:
                if tag == "br":
                    if run is not None:
                        run.append(" ")
                    continue
                k = stack.last((tag,))
                if k and not (tag in INLINE and stack.blocks[-1] > k):
                    if stack.blocks[-1] >= k:
                        run = None
                    stack.cut(k)
                continue
            if tag in SKIPPED:
                if attributes.endswith("/") and tag in ("svg", "math", "object"):
                    continue
                close = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
                at = close.end() if close else length
                continue
            if tag in VOID:
                if tag in ("br", "hr") and run is not None:
                    run.append(" ")
                if tag == "hr":
                    run = None
                continue
            if tag == "html":
                continue
            if tag in INLINE:
                if tag == "a":
                    self.links[stack.nodes[-1]] += 1
                stack.push(tag, stack.nodes[-1])
                continue
            if tag in CLOSES_P:
                stack.close(frozenset(["p"]), BARRIER)
            if tag in ENDS:
                stack.close(*ENDS[tag])
            stack.push(tag, self._node(tag, stack.nodes[-1], attributes))
            run = None

    def features(self) -> list[tuple[str, ...]]:
        """What is known of each node beside its neighbours' labels: names, and shape alone, which holds where names say nothing."""
        n, parent = len(self.tag), self.parent
        total, linked, links, stops, heading, long_ = self.own[:], self.linked[:], self.links[:], self.stops[:], [""] * n, [0] * n
        for k in range(n - 1, 0, -1):
            for count in (total, linked, links, stops):
                count[parent[k]] += count[k]
            if self.tag[k] in ("h1", "h2", "h3"):
                heading[parent[k]] = self.tag[k]
            long_[parent[k]] += self.own[k] >= 80 and 3 * self.linked[k] < self.own[k]
        page = max(1, total[0])
        part, out, first = [""] * n, [], {}
        for k in range(n):
            up = parent[k]
            if k:
                part[k] = self.tag[up] if self.tag[up] in PARTS else part[up]
                first.setdefault(up, k)
            share = int(3.999 * linked[k] / total[k]) if total[k] else -1
            size = min(9, total[k].bit_length())
            prose = "none" if not stops[k] else "much" if 120 * stops[k] >= total[k] >= 40 else "some"
            begin = self.start[k] / page
            found = [
                f"<{self.tag[k]} links {share}",
                f"own {min(5, int(math.log2(self.own[k] / 16 + 1)))}",
                f"prose {prose} size {size}",
                f"<{self.tag[k]} in {part[k]}",
                f"share {int(9.999 * total[k] / page)}",
                f"begin {int(9.999 * min(begin, 1.0))} prose {prose}",
                f"links {min(4, links[k].bit_length())} prose {prose}",
                "named" if self.names[k] else "unnamed",
                *self.names[k],
            ]
            if k:
                found += [
                    f"beside prose {min(3, long_[up])} <{self.tag[k]}",
                    f"beside <{heading[up]} <{self.tag[k]}",
                    f"beside links {int(3.999 * linked[up] / total[up]) if total[up] else -1} own {share}",
                    f"rest {int(4.999 * max(0.0, 1 - begin - total[k] / page))} prose {prose}",
                ]
            if self.tag[k] in ("h1", "h2", "h3"):
                found += [f"<{self.tag[k]} in {part[k]} first {first.get(up) == k}"]
            out.append(tuple(found))
        for node, pieces in self.text:
            head = "".join(pieces[:2]).lstrip()[:1]
            if head in "©®":
                out[node] = (*out[node], "begins with a right") if head else out[node]
        return out

    def labels(self) -> list[int]:
        """Labels of a training page: that of the nearest labelled element; what holds main text is main text too."""
        out = [0] * len(self.tag)
        for k in range(len(out)):
            given = self.label[k]
            out[k] = given if given is not None else (out[self.parent[k]] if k else 0)
        for k in range(len(out) - 1, 0, -1):
            if out[k]:
                out[self.parent[k]] = 1
        return out


class TreeModel:
    """Log potentials: root[y], pair[parent y][child y], and own[feature] = (for y = 0, for y = 1)."""

    def __init__(self, root: tuple[float, float], pair: tuple[tuple[float, float], tuple[float, float]], own: dict[str, tuple[float, float]]):
        self.root, self.pair, self.own = root, pair, own

    @staticmethod
    def learn(pages: list[str], turns: int = TURNS, batch: int = 60, rate: float = 0.04, ridge: float = 3e-4, seed: int = 3) -> TreeModel:
        """The potentials that make the labels of the pages likeliest: the gradient of a potential is how often the messages expect
        it less how often it is met. Messages of many pages pass together, a depth at a time.
        """
        known: dict[str, int] = {}
        trees = []
        for page in pages:
            dom = Dom(page, labelled=True)
            rows = [[known.setdefault(name, len(known)) for name in found] for found in dom.features()]
            depth = [0] * len(rows)
            for k in range(1, len(rows)):
                depth[k] = depth[dom.parent[k]] + 1
            flat = np.fromiter((x for row in rows for x in row), np.int64)
            trees.append((flat, np.fromiter(map(len, rows), np.int64, len(rows)), np.array(dom.parent), np.array(depth), np.array(dom.labels())))
        often = np.bincount(np.concatenate([t[0] for t in trees]), minlength=len(known)) >= 5
        # One vector of all: own potentials, pair[0][0] .. pair[1][1], root.
        theta = np.zeros(len(known) + 5)
        theta[-5:] = (0.0, -4.0, -1.0, 0.0, 0.0)
        free = np.append(often, [True] * 5)
        draw, first, second, step = np.random.default_rng(seed), np.zeros(len(theta)), np.zeros(len(theta)), 0
        for _ in range(turns):
            order = draw.permutation(len(trees))
            for i in range(0, len(order), batch):
                step += 1
                some = [trees[k] for k in order[i : i + batch]]
                g = _gradient(theta, some, len(known)) / len(some) + ridge * theta * (np.arange(len(theta)) < len(known))
                first, second = 0.9 * first + 0.1 * g, 0.99 * second + 0.01 * g * g
                theta -= rate * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-6) * free
        p = theta[-5:].tolist()
        return TreeModel((0.0, p[4]), ((p[0], p[1]), (p[2], p[3])), {name: (0.0, float(theta[k])) for name, k in known.items() if theta[k]})

    def marginals(self, dom: Dom) -> list[float]:
        """P(main text) of each node, by one pass of messages up the tree and one down."""
        n, none = len(dom.tag), (0.0, 0.0)
        found = [[self.own.get(f, none) for f in names] for names in dom.features()]
        up0, up1 = [sum(f[0] for f in x) for x in found], [sum(f[1] for f in x) for x in found]
        (p00, p01), (p10, p11) = self.pair
        to0, to1 = [0.0] * n, [0.0] * n  # messages of each node to its parent
        for k in range(n - 1, 0, -1):
            to0[k] = _log_sum(p00 + up0[k], p01 + up1[k])
            to1[k] = _log_sum(p10 + up0[k], p11 + up1[k])
            up0[dom.parent[k]] += to0[k]
            up1[dom.parent[k]] += to1[k]
        down0, down1 = [0.0] * n, [0.0] * n
        down0[0], down1[0] = self.root
        out = [0.0] * n
        for k in range(n):
            if k:
                j = dom.parent[k]
                a, b = down0[j] + up0[j] - to0[k], down1[j] + up1[j] - to1[k]
                down0[k], down1[k] = _log_sum(a + p00, b + p10), _log_sum(a + p01, b + p11)
            gap = down0[k] + up0[k] - down1[k] - up1[k]
            out[k] = 1 / (1 + math.exp(min(gap, 700.0)))
        return out

    def text(self, page: str | None) -> str:
        if not page:
            return ""
        dom = Dom(page)
        marginal = self.marginals(dom)
        runs = (" ".join("".join(pieces).split()) for node, pieces in dom.text if marginal[node] > 0.5)
        return " ".join(r for r in runs if r)


def _gradient(theta: np.ndarray, trees: list[tuple[np.ndarray, ...]], n_own: int) -> np.ndarray:
    """Of the negative log-likelihood of the labels of some trees (flat features, features a node, parent, depth, label)."""
    size = np.array([len(t[1]) for t in trees])
    offset = np.repeat(np.cumsum(size) - size, size)
    flat, count, depth, y = (np.concatenate([t[k] for t in trees]) for k in (0, 1, 3, 4))
    parent = np.concatenate([t[2] for t in trees]) + offset
    node = np.repeat(np.arange(len(count)), count)
    n = len(count)
    p00, p01, p10, p11, root = theta[n_own:]
    up0, up1 = np.zeros(n), np.bincount(node, theta[flat], n)
    to0, to1, down0, down1 = (np.zeros(n) for _ in range(4))
    down1[depth == 0] = root
    levels = [np.flatnonzero(depth == d) for d in range(1, int(depth.max(initial=0)) + 1)]
    for at in reversed(levels):
        to0[at], to1[at] = np.logaddexp(p00 + up0[at], p01 + up1[at]), np.logaddexp(p10 + up0[at], p11 + up1[at])
        up0 += np.bincount(parent[at], to0[at], n)
        up1 += np.bincount(parent[at], to1[at], n)
    out = np.zeros(len(theta))
    for at in levels:
        j = parent[at]
        a, b = down0[j] + up0[j] - to0[at], down1[j] + up1[j] - to1[at]
        down0[at], down1[at] = np.logaddexp(a + p00, b + p10), np.logaddexp(a + p01, b + p11)
        both = np.stack((a + p00 + up0[at], a + p01 + up1[at], b + p10 + up0[at], b + p11 + up1[at]))
        both = np.exp(both - both.max(axis=0))
        out[n_own : n_own + 4] += (both / both.sum(axis=0)).sum(axis=1) - np.bincount(2 * y[j] + y[at], minlength=4)
    marginal = 1 / (1 + np.exp(np.clip(down0 + up0 - down1 - up1, -500, 500)))
    out[:n_own] += np.bincount(flat, (marginal - y)[node], n_own)
    out[n_own + 4] += (marginal - y)[depth == 0].sum()
    return out


def _log_sum(a: float, b: float) -> float:
    return a + math.log1p(math.exp(b - a)) if a > b else b + math.log1p(math.exp(a - b))


@lru_cache(maxsize=4)
def fit(pages: int = TRAINING_PAGES, seed: int = 0) -> TreeModel:
    """The model of generated pages; no table has a part in it, so that one fit serves a process."""
    return TreeModel.learn(labelled_pages(pages, seed))


def extracted(pages: DataFrame, model: TreeModel | None = None, markup: str = "html", keep: list[str] | None = None) -> DataFrame:
    """pages (or their columns in keep) with text, the main text, and n_chars, its code points."""
    shipped = pages.sparkSession.sparkContext.broadcast(model or fit())
    kept = [c for c in (pages.columns if keep is None else keep) if c.lower() not in ("text", "n_chars")]

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                part = batch.slice(i, 500)
                texts = [shipped.value.text(v) for v in part.column(markup).to_pylist()]
                yield with_columns(part, {"text": pa.array(texts, pa.string()), "n_chars": pa.array(map(len, texts), pa.int64())}, kept)

    return pages.select(*dict.fromkeys([*kept, markup])).mapInArrow(run, extended(pages, "text string, n_chars long", kept))


def op1_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extracted(table(spark, sf_dir, "pages"), keep=["page_id", "url"]).select("page_id", "url", "text", "n_chars")
