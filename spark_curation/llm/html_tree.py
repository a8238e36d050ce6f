"""Main-text extraction with a graphical model over the DOM tree.

Every block element is a binary variable: part of the article or not. Node potentials
look at the element itself, parent-child potentials at how labels go together along an
edge. Sum-product messages passed once upward and once downward give exact marginals
on the tree, and text of elements that are more likely content than not is kept. The
weights come from labelled pages by the gradient of the log-likelihood, whose
expectations are the same marginals.
"""

from __future__ import annotations

import functools
import html
import math
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spark_curation.llm.markup import ATTRIBUTE, Scanner

#: Elements by role in a page.
BLOCKS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption search".split())
DROPPED = frozenset("script style title noscript template iframe select textarea button datalist".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
ENDS_P = BLOCKS - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption"}
#: Elements that an opening tag ends when they are still open, and elements the search for them stops at.
IMPLIED = {"li": ({"li"}, {"ul", "ol", "menu"}), "dd": ({"dd", "dt"}, {"dl"}), "dt": ({"dd", "dt"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: Words in class, id and role that speak for a kind of block.
HINTS = {
    "content": "article content post entry story main body text prose page-content post-body".split(),
    "menu": "nav navbar navigation menu breadcrumb breadcrumbs toc pagination pager tabs toolbar skip".split(),
    "ad": "ad ads advert adverts advertisement advertising sponsor sponsored promo promoted promotion adsense dfp".split(),
    "comment": "comment comments commentlist reply replies respond disqus discussion responses".split(),
    "aside": "sidebar side widget widgets related recommended rail aside more trending popular teaser complementary".split(),
    "notice": "cookie cookies consent gdpr notice popup modal overlay alert banner newsletter subscribe signup paywall toast".split(),
    "share": "share sharing social follow".split(),
    "footer": "footer foot copyright legal contentinfo bottom colophon".split(),
    "header": "header masthead topbar top logo brand".split(),
    "form": "form search login register contact-form searchform".split(),
}
_HINT = {w: k for k, ws in HINTS.items() for w in ws}
_TOKEN = re.compile(r"[a-z]+(?:-[a-z]+)*")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_ENDED = re.compile(r"[.!?…。！？]")


class Tree:
    """Block elements in page order as parallel lists, and the text runs that hang on them.

    Tolerates unclosed and misnested tags. Text or a block outside a body opens one. Inline
    elements leave no node; their text goes to the nearest block, and so do the words
    inside links for the share of linked text. Open elements are found by name, so that
    reading takes time in proportion to the page.
    """

    def __init__(self, page: str) -> None:
        self.parent, self.tag, self.hints, self.label = [-1], ["root"], [()], [0]
        self.words, self.linked, self.ends = [0], [0], [0]
        self.runs: list[tuple[int, str]] = []
        self._open: list[tuple[str, int]] = [("root", 0)]
        #: By name of a block, where it stands among the open ones.
        self._where: dict[str, list[int]] = {}
        #: How many blocks were open when the link began that is open now; 0 if there is none.
        self._link = 0
        self._buffer: list[str] = []
        for text, name, more in Scanner(page, DROPPED):
            self._data(text)
            if name[:1] == "/":
                self._end(name[1:])
            elif name and name not in DROPPED and name != "!":
                self._start(name, more)
        self._flush()

    def _flush(self) -> None:
        if self._buffer:
            text = " ".join("".join(self._buffer).split())
            self._buffer.clear()
            if text:
                at = self._open[-1][1]
                self.runs.append((at, text))
                self.words[at] += text.count(" ") + 1
                self.ends[at] += len(_ENDED.findall(text))

    def _pop_to(self, depth: int) -> None:
        self._flush()
        while len(self._open) > depth:
            self._where[self._open.pop()[0]].pop()
        if self._link > depth:
            self._link = 0

    def _innermost(self, names) -> int:
        return max((w[-1] for n in names if (w := self._where.get(n))), default=-1)

    def _close_implied(self, tag: str) -> None:
        if tag in IMPLIED:
            ends, stops = IMPLIED[tag]
            at = self._innermost(ends)
            if at > self._innermost(stops):
                self._pop_to(at)
        elif tag in ENDS_P and self._open[-1][0] == "p":
            self._pop_to(len(self._open) - 1)

    def _push(self, tag: str, hints: tuple[str, ...], label: int | None) -> None:
        above = self._open[-1][1]
        self.parent.append(above)
        self.tag.append(tag)
        self.hints.append(hints)
        self.label.append(self.label[above] if label is None else label)
        for x in (self.words, self.linked, self.ends):
            x.append(0)
        self._where.setdefault(tag, []).append(len(self._open))
        self._open.append((tag, len(self.parent) - 1))

    def _start(self, tag: str, attrs: str) -> None:
        if tag == "br" or tag == "hr":
            return self._flush()
        if tag == "a":
            self._link = len(self._open)
        if tag not in BLOCKS:
            return None
        if tag not in ("html", "body") and not self._where.get("body"):
            self._push("body", (), None)
        self._close_implied(tag)
        self._flush()
        get = {k.lower(): html.unescape(a or b or c) for k, a, b, c in ATTRIBUTE.findall(attrs)} if attrs and not attrs.isspace() else {}
        named = " ".join(get.get(k, "") for k in ("class", "id", "role", "itemprop")) if get else ""
        hints: set[str] = set()
        for w in _TOKEN.findall(_CAMEL.sub("-", named).lower().replace("_", "-")):
            hints.update(_HINT[p] for p in (w, *w.split("-")) if p in _HINT)
        if tag in ("html", "body") and self._where.get(tag):
            return None
        return self._push(tag, tuple(sorted(hints)), int(get["data-y"]) if "data-y" in get else None)

    def _end(self, tag: str) -> None:
        if tag == "a":
            self._link = 0
        elif tag not in ("html", "body") and (w := self._where.get(tag)):
            self._pop_to(w[-1])

    def _data(self, data: str) -> None:
        if not data:
            return
        if "&" in data:
            data = html.unescape(data)
        if not self._where.get("body") and not data.isspace():
            self._push("body", (), None)
        self._buffer.append(data)
        if self._link:
            self.linked[self._open[-1][1]] += len(data.split())


def tree(page: str | None) -> Tree:
    return Tree((page or "").replace("\0", ""))


_GROUP = {f"h{i}": "h" for i in range(2, 7)} | dict.fromkeys("ul ol dl menu".split(), "list") | dict.fromkeys("li dt dd".split(), "item") | dict.fromkeys("table tbody thead tfoot tr td th caption".split(), "table") | dict.fromkeys("blockquote pre figcaption".split(), "quote")


_VALUES = {
    "tag": sorted({_GROUP.get(t, t) for t in BLOCKS} | {"root"}),
    "hint": sorted(HINTS),
    "links": ["none", "few", "half", "all"],
    "words": ["0", "1", "5", "20", "80"],
    "ends": ["0", "1", "3"],
    "shape": ["leaf", "inner"],
    "bare": sorted({_GROUP.get(t, t) for t in BLOCKS} | {"root"}),
    "framed": sorted({_GROUP.get(t, t) for t in BLOCKS} | {"root"}),
}
#: Number of each feature, in a fixed order.
FEATURES = {name: i for i, name in enumerate(["bias", *[f"{k}={v}" for k, vs in _VALUES.items() for v in vs]])}
_TAG = {t: FEATURES[f"tag={_GROUP.get(t, t)}"] for t in [*BLOCKS, "root"]}
_HINTED = {h: FEATURES[f"hint={h}"] for h in HINTS}
_LINKS, _WORDS, _ENDS, _SHAPE = (FEATURES[f"{k}={_VALUES[k][0]}"] for k in ("links", "words", "ends", "shape"))
#: Features of elements of pages with and without an element marked as the content.
_FRAME = {b: {t: FEATURES[f"{'bare' if b else 'framed'}={_GROUP.get(t, t)}"] for t in [*BLOCKS, "root"]} for b in (True, False)}


def bare(t: Tree) -> bool:
    """Whether no element of a page is marked as its content."""
    return not any((x in ("article", "main") or "content" in h) and "comment" not in h for x, h in zip(t.tag, t.hints, strict=True))


class Forest:
    """Nodes of many trees as arrays, parents before children, with the features that hold for each node."""

    def __init__(self, trees: list[Tree]):
        sizes = np.array([len(t.parent) for t in trees], np.int64)
        self.first = np.concatenate([[0], np.cumsum(sizes)])
        n = self.n = int(self.first[-1])
        flat = lambda name: np.fromiter((x for t in trees for x in getattr(t, name)), np.int64, n)
        parent, base = flat("parent"), np.repeat(self.first[:-1], sizes)
        self.parent = np.where(parent < 0, -1, parent + base)
        self.label = flat("label")
        depth = [0] * n
        up = self.parent.tolist()
        for i, p in enumerate(up):
            if p >= 0:
                depth[i] = depth[p] + 1
        depth = np.array(depth, np.int64)
        order = np.argsort(depth, kind="stable")
        #: Nodes of each depth below the roots; where most hold few nodes, steps go from node to node.
        self.levels = np.split(order, np.searchsorted(depth[order], np.arange(1, (depth.max() if n else 0) + 1)))[1:] if n else []
        self.narrow = len(self.levels) * 16 > n
        words, linked, ends, below = flat("words"), flat("linked"), flat("ends"), np.zeros(n, np.int64)
        if self.narrow:
            columns = [x.tolist() for x in (words, linked, ends, below)]
            for i in range(n - 1, -1, -1):
                if (p := up[i]) >= 0:
                    for x in columns:
                        x[p] += x[i]
                    columns[3][p] += 1
            words, linked, ends, below = (np.array(x, np.int64) for x in columns)
        else:
            for level in reversed(self.levels):
                p = self.parent[level]
                for x, add in ((words, words[level]), (linked, linked[level]), (ends, ends[level]), (below, below[level] + 1)):
                    np.add.at(x, p, add)
        share = linked / np.maximum(words, 1)
        every = [
            np.zeros(n, np.int64),
            np.fromiter((_TAG[x] for t in trees for x in t.tag), np.int64, n),
            _LINKS + np.where(linked == 0, 0, 1 + (share >= 0.3) + (share >= 0.7)),
            _WORDS + np.searchsorted([1, 5, 20, 80], words, "right"),
            _ENDS + np.searchsorted([1, 3], ends, "right"),
            _SHAPE + (below > 0),
            np.fromiter((of[x] for t in trees for of in [_FRAME[bare(t)]] for x in t.tag), np.int64, n),
        ]
        hints = [(b + i, _HINTED[h]) for b, t in zip(self.first[:-1].tolist(), trees, strict=True) for i, hs in enumerate(t.hints) for h in hs]
        self.at = np.concatenate([np.tile(np.arange(n), len(every)), np.array([a for a, _ in hints], np.int64)])
        self.feature = np.concatenate([*every, np.array([f for _, f in hints], np.int64)])

    def scores(self, weights: np.ndarray) -> np.ndarray:
        return np.bincount(self.at, weights[self.feature], self.n)

    def beliefs(self, node: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Exact chances of label 1 for all nodes, and of the four label pairs for all edges to parents, by sum-product.

        ``node`` has log odds of label 1; ``edge[a, b]`` is the log potential of a
        parent labelled a over a child labelled b. One sweep goes up, one goes down.
        """
        if self.narrow:
            full, up, rest = self._one_by_one(node.tolist(), edge.tolist())
            return self._chances(full, up, rest, edge)
        up, sent, full = node.copy(), np.zeros(self.n), np.zeros(self.n)
        for level in reversed(self.levels):
            u = up[level]
            sent[level] = np.logaddexp(edge[1, 0], edge[1, 1] + u) - np.logaddexp(edge[0, 0], edge[0, 1] + u)
            np.add.at(up, self.parent[level], sent[level])
        full[self.parent < 0] = up[self.parent < 0]
        rest = np.zeros(self.n)
        for level in self.levels:
            q = rest[level] = full[self.parent[level]] - sent[level]
            full[level] = up[level] + np.logaddexp(edge[0, 1], edge[1, 1] + q) - np.logaddexp(edge[0, 0], edge[1, 0] + q)
        return self._chances(full, up, rest, edge)

    def _one_by_one(self, up: list[float], edge: list[list[float]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The same sweeps for trees that are deep and narrow."""

        def either(x: float, y: float) -> float:
            return max(x, y) + math.log1p(math.exp(-abs(x - y)))

        (a, b), (c, d) = edge
        parent, sent, rest = self.parent.tolist(), [0.0] * self.n, [0.0] * self.n
        for i in range(self.n - 1, -1, -1):
            if (p := parent[i]) >= 0:
                sent[i] = either(c, d + up[i]) - either(a, b + up[i])
                up[p] += sent[i]
        full = list(up)
        for i, p in enumerate(parent):
            if p >= 0:
                q = rest[i] = full[p] - sent[i]
                full[i] = up[i] + either(b, d + q) - either(a, c + q)
        return np.array(full), np.array(up), np.array(rest)

    def _chances(self, full: np.ndarray, up: np.ndarray, rest: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        kids = np.flatnonzero(self.parent >= 0)
        z = np.stack([edge[a, b] + a * rest[kids] + b * up[kids] for a in (0, 1) for b in (0, 1)])
        pairs = np.exp(z - z.max(axis=0, initial=-np.inf))
        return 1 / (1 + np.exp(-np.clip(full, -60, 60))), pairs / pairs.sum(axis=0)


class Model:
    """Weights of node features and of the four label pairs along an edge."""

    def __init__(self) -> None:
        self.node, self.edge = np.zeros(len(FEATURES)), np.zeros((2, 2))

    def content(self, trees: list[Tree]) -> list[np.ndarray]:
        """Chance of being content for the nodes of each tree."""
        forest = Forest(trees)
        chance = forest.beliefs(forest.scores(self.node), self.edge)[0]
        return np.split(chance, forest.first[1:-1])

    def extract(self, pages: list[str | None]) -> list[str]:
        """For each page the text of the blocks that are more likely content than not, in page order."""
        trees = [tree(p) for p in pages]
        if not trees:
            return []
        return [" ".join([text for at, text in t.runs if chance[at] > 0.5]) for t, chance in zip(trees, self.content(trees), strict=True)]


def train(pages: list[str], rounds: int = 400, rate: float = 0.3, ridge: float = 1e-4) -> Model:
    """A model fitted to pages whose elements carry their label in ``data-y`` (inherited downward).

    Follows the gradient of the log-likelihood: what the labels show less what the
    model's own marginals expect.
    """
    forest, model = Forest([tree(p) for p in pages]), Model()
    kids = np.flatnonzero(forest.parent >= 0)
    shown = 2 * forest.label[forest.parent[kids]] + forest.label[kids]
    counts = np.bincount(shown, minlength=4)
    seen_n, seen_e = np.full(len(FEATURES), 1e-8), np.full(4, 1e-8)
    for _ in range(rounds):
        one, pairs = forest.beliefs(forest.scores(model.node), model.edge)
        g_n = np.bincount(forest.feature, (forest.label - one)[forest.at], len(FEATURES)) / forest.n - ridge * model.node
        g_e = (counts - pairs.sum(axis=1)) / forest.n - ridge * model.edge.ravel()
        seen_n += g_n**2
        seen_e += g_e**2
        model.node += rate * g_n / np.sqrt(seen_n)
        model.edge += (rate * g_e / np.sqrt(seen_e)).reshape(2, 2)
    return model


def labelled_page(r: random.Random) -> str:
    """A made-up page in one of many layouts, each element labelled in ``data-y``."""
    word = lambda: "".join(r.choice("ka lo mi ter sun ve ra do pli en ost ar ui ne".split()) for _ in range(r.randrange(1, 4)))
    words = lambda a, b: " ".join(word() for _ in range(r.randrange(a, b)))
    says = lambda n: " ".join(words(3, 15).capitalize() + r.choice("...!?") for _ in range(n))
    link = lambda: f'<a href="/{word()}">{words(1, 4)}</a>'
    items = lambda a, b: "".join(f"<li>{link()}</li>" for _ in range(r.randrange(a, b)))
    named = lambda kind: r.choice([f'class="{w}"', f'id="{w}"', f'class="{word()} {w}-{word()}"'][: r.choice([2, 3])]) if (w := r.choice(HINTS[kind])) else ""
    para = lambda: r.choice([f"<p>{says(r.randrange(1, 8))}</p>"] * 6 + [f"<p>{says(2)} {link()} {says(2)}</p>", f"<p>{words(1, 6).capitalize()}.", f"<p><b>{says(1)}<br>", f"<blockquote><p>{says(2)}</p></blockquote>", f"<h2>{words(2, 6)}</h2>", f"<ul>{''.join(f'<li>{says(1)}</li>' for _ in range(r.randrange(2, 6)))}</ul>", f"<table><tr><th>{words(1, 3)}</th><td>{words(1, 5)}</td></tr><tr><td>{words(1, 3)}</td><td>{r.randrange(99)}</td></tr></table>", f"<div>{says(3)}</div>", f"<figure><img src=x><figcaption>{words(3, 9)}.</figcaption></figure>", f"<pre>{words(2, 9)}</pre>", f"<h3>{words(1, 4)}</h3><ul>{items(1, 9)}</ul>", f"<ul>{items(1, 9)}</ul>", f"<ol>{items(2, 5)}</ol>", f'<p class="{r.choice(["byline", "author", "meta", "dateline", "tags"])}">{words(1, 7)}</p>', f'<div class="{r.choice(["byline", "author", "post-meta"])}">{link()} {words(1, 4)}</div>', f"<dl><dt>{words(1, 3)}</dt><dd>{words(1, 9)}</dd></dl>", f"<div hidden><p>{says(2)}</p></div>", f"<p>{words(1, 150)}</p>", f"<p>{words(1, 30)}</p>", f"<p>{' | '.join(words(1, 3) for _ in range(r.randrange(3, 40)))}</p>", f"<p>{word()} " + f"{word()}### " * r.randrange(1, 60) + "</p>"])
    ad = lambda: f'<div {named("ad")} data-y="0">{r.choice([says(1), says(2), says(3), link(), words(2, 9)])}</div>'
    menu = lambda: r.choice([f'<nav data-y="0"><ul>{items(2, 9)}</ul></nav>', f'<div {named("menu")} data-y="0"><ul>{items(2, 9)}</ul></div>', f'<ul {named("menu")} data-y="0">{items(2, 9)}</ul>', f'<nav data-y="0">{" | ".join(link() for _ in range(r.randrange(2, 7)))}</nav>'])
    foot = lambda: r.choice([f'<footer data-y="0">{r.choice([f"&copy; {word()}.com &middot; {says(1)}", f"<p>{says(2)}</p>", f"<ul>{items(2, 6)}</ul>", says(2)])}</footer>', f'<div {named("footer")} data-y="0"><p>&copy; {words(2, 5)}. {says(1)}</p></div>'])
    head = lambda: r.choice([f'<header data-y="0">{link()}<p>{words(2, 7)}</p></header>', f'<div {named("header")} data-y="0">{link()} {words(1, 5)}</div>', ""])
    side = lambda: r.choice([f'<aside data-y="0"><h3>{words(1, 4)}</h3>{r.choice([f"<ul>{items(2, 7)}</ul>", f"<p>{says(2)}</p>"])}</aside>', f'<div {named("aside")} data-y="0"><h3>{words(1, 4)}</h3>{r.choice([f"<ul>{items(2, 7)}</ul>", f"<p>{says(2)}</p>"])}</div>'])
    note = lambda: f'<div {named("notice")} data-y="0"><p>{says(r.randrange(1, 3))}</p>{link()}</div>'
    form = lambda: r.choice([f'<form data-y="0"><p>{words(2, 8)}</p><label>{words(1, 3)}</label><input name=q><button>{word()}</button></form>', f'<div {named("form")} data-y="0"><form><label>{words(1, 4)}</label><input></form></div>'])
    share = lambda: f'<div {named("share")} data-y="0">{" ".join(link() for _ in range(r.randrange(2, 5)))}</div>'
    reply = lambda: r.choice([f"<li><p>{says(2)}</p></li>", f'<div class="comment"><b>{word()}</b><p>{says(2)}</p></div>', f'<article class="comment"><p>{says(3)}</p></article>'])
    talk = lambda: r.choice([f'<section {named("comment")} data-y="0"><h2>{words(1, 3)}</h2>{"".join(reply() for _ in range(r.randrange(1, 5)))}</section>', f'<div {named("comment")} data-y="0"><h3>{words(1, 3)}</h3><ol>{"".join(reply() for _ in range(r.randrange(1, 5)))}</ol></div>'])
    body = [f"<h1>{words(2, 9)}</h1>"] * r.choice([1, 1, 1, 0]) + [para() for _ in range(r.choice([1, 1, 2, r.randrange(1, 14), r.randrange(1, 14)]))]
    for extra in (ad, share, side, note, form, talk):
        if r.random() < 0.2:
            body.insert(r.randrange(1, len(body) + 1), extra())
    inner = "".join(body)
    main = r.choice([f'<article data-y="1">{inner}</article>'] * 2 + [f'<main data-y="1">{inner}</main>', f'<div {named("content")} data-y="1">{inner}</div>', f'<main data-y="0">{side()}<article data-y="1">{inner}</article></main>', f'<section {named("content")} data-y="1">{inner}</section>'])
    before = [x() for x in r.sample([head, menu, ad, note, side, form, share], r.randrange(1, 5))]
    after = [x() for x in r.sample([talk, side, ad, menu, note, form, share], r.randrange(0, 4))] + [foot()] * r.choice([1, 1, 0])
    top = 0
    if r.random() < 0.35:  # no element is marked as the article; text may even stand in the body itself
        main, top = r.choice([inner, inner, f"<div>{inner}</div>", f"<div>{inner}</div>", says(r.randrange(1, 9)), words(1, 60), f"<p>{words(1, 6).capitalize()}.</p>"]), 1
        before, after = before[: r.choice([0, 1, 2])], after[-r.choice([1, 1, 2]) :] if r.random() < 0.7 else []
    if r.random() < 0.4:
        before, after = ['<div id="wrap">', *before], [*after, "</div>"]
    return f"<!DOCTYPE html><html><head><title>{words(2, 6)}</title></head><body data-y='{top}'>{''.join(before)}{main}{''.join(after)}</body></html>"


@functools.cache
def default_model(pages: int = 600, seed: int = 7) -> Model:
    """The model trained on ``pages`` made-up labelled pages; the same weights for the same arguments."""
    r = random.Random(seed)
    return train([labelled_page(r) for _ in range(pages)])


#: Pages whose trees are worked on at once.
TOGETHER = 128


def extract(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """``(page_id, url, text, n_chars)`` for every row of ``pages``.

    A null page, or one without content, has the empty text. Repeated rows and nulls in other columns are kept, an empty table gives
    none, further columns are ignored.
    """
    model = model or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, TOGETHER):
                part = b.slice(at, TOGETHER)
                texts = model.extract(part.column(2).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
