"""Main text of HTML pages by a tree-structured graphical model.

Each block element and each text run is a variable, content or not. Its own potential is a weighted sum of features (element,
names in class, id and role, link share, length, ends of sentences); parent and child share a potential of 2 x 2
weights, one table for elements and one for runs. Messages go up from the leaves and down from the root (sum-product) and
give exact marginals; runs with a marginal of one half or more are the main text. Weights maximise the likelihood of
labelled pages, whose gradient uses the same marginals.

Training pages come from ``page_maker`` (``TRAIN_PAGES``, a fixed number) or from the caller.

Defined cases: null and empty html give an empty text; broken markup is read as browsers roughly do; a page without text gives an
empty text; repeated rows each give a row; null ids and urls pass through. An empty table gives no rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dom import Node, parse
from .page_maker import MARK, labelled_pages

TRAIN_PAGES = 400
TAGS = "#root body article main section div p h1 h2 h3 h4 ul ol li nav header footer aside form table tr td blockquote pre figure figcaption button label dl dd details other".split()
# Words in class, id and role that often mark parts of a page.
NAMES = {
    "good": "article content entry post story text main body page prose",
    "nav": "nav navbar navigation menu topnav breadcrumb breadcrumbs pagination pager toc tabs sitemap skip",
    "head": "header masthead logo branding topbar site-title hero",
    "foot": "footer copyright colophon bottom legal",
    "side": "sidebar side aside widget widgets related recommended recommendations trending popular rail more",
    "ad": "ad ads advert adverts advertisement advertising adsense adslot sponsor sponsored promo promotion banner affiliate dfp taboola outbrain",
    "notice": "cookie cookies notice consent gdpr alert popup modal overlay privacy disclaimer warning message paywall",
    "form": "search form newsletter signup subscribe subscription login register contact",
    "share": "share social sharing tags tag follow like likes rating buttons toolbar",
    "comment": "comment comments commentlist commentbody reply replies respond responses response disqus discussion thread feedback",
    "author": "author byline meta date dateline time",
    "box": "container wrapper wrap inner outer row col column grid box layout",
}
_WORD = re.compile(r"[a-z]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_OF = {w: k for k, ws in NAMES.items() for w in ws.split()}
_LONG = (8, 25, 80, 250, 1000)
_FEATURES: dict[str, int] = {}
for _n in ["e", "t", *(f"{a}:{t}" for a in ("tag", "in", "up") for t in TAGS), *(f"{a}:{n}" for a in ("name", "under") for n in NAMES), "hidden", *(f"{a}links{k}" for a in "et" for k in range(4)), *(f"{a}long{k}" for a in "et" for k in range(len(_LONG) + 1)), "stop", "copy", "words1", "first"]:
    _FEATURES[_n] = len(_FEATURES)
_ANY = {t: (t if t in TAGS else {"h5": "h4", "h6": "h4", "th": "td", "tbody": "table", "thead": "table", "tfoot": "table", "dt": "dd", "menu": "ul", "html": "body", "fieldset": "form", "legend": "label", "select": "form", "option": "label", "center": "div", "summary": "details"}.get(t, "other")) for t in "html h5 h6 th tbody thead tfoot dt menu fieldset legend select option center summary".split()}


@lru_cache(100_000)
def _names(raw: str) -> tuple[str, ...]:
    return tuple(sorted({_OF[w] for w in _WORD.findall(_CAMEL.sub(" ", raw).lower()) if w in _OF}))


def _tag(tag: str) -> str:
    return tag if ("tag:" + tag) in _FEATURES else _ANY.get(tag, "other")


def _bucket(k: int) -> int:
    return next((i for i, n in enumerate(_LONG) if k < n), len(_LONG))


def _links(node: Node) -> int:
    share = node.linked / node.chars if node.chars else 0
    return 0 if share == 0 else 1 if share < 0.3 else 2 if share < 0.75 else 3


def node_features(nodes: list[Node]) -> list[list[int]]:
    """Numbers of the active features of each node."""
    f, out = _FEATURES, []
    named: list[tuple[str, ...]] = []
    for n in nodes:
        if n.tag == "#text":
            got = [f["t"], f["in:" + _tag(nodes[n.parent].tag)], f[f"tlinks{_links(n)}"], f[f"tlong{_bucket(n.chars)}"]]
            got += [f["under:" + x] for x in named[n.parent]]
            if n.text[-1] in ".!?…\"”:;":
                got.append(f["stop"])
            if "©" in n.text[:40]:
                got.append(f["copy"])
            if " " not in n.text:
                got.append(f["words1"])
            named.append(())
        else:
            a = n.attrs
            names = _names(f"{a.get('class', '')} {a.get('id', '')} {a.get('role', '')}") if a else ()
            named.append(names)
            got = [f["e"], f["tag:" + _tag(n.tag)], f[f"elinks{_links(n)}"], f[f"elong{_bucket(n.chars)}"]]
            got += [f["name:" + x] for x in names]
            if n.parent >= 0:
                got.append(f["up:" + _tag(nodes[n.parent].tag)])
            if a and ("hidden" in a or a.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", a.get("style", ""))):
                got.append(f["hidden"])
        out.append(got)
    return out


class Forest:
    """Many pages' trees at once; a level is all nodes of one depth."""

    def __init__(self, pages: list[list[Node]]):
        keep: list[Node] = []
        active: list[list[int]] = []
        parent: list[int] = []
        self.first = [0]
        for nodes in pages:
            place: dict[int, int] = {}
            for k, (n, a) in enumerate(zip(nodes, node_features(nodes), strict=True)):
                if n.chars or k == 0:  # what has no text says nothing
                    place[k] = len(keep)
                    keep.append(n)
                    active.append(a)
                    parent.append(place[n.parent] if n.parent >= 0 else -1)
            self.first.append(len(keep))
        self.nodes, self.parent = keep, np.asarray(parent)
        self.owner = np.repeat(np.arange(len(active)), [len(a) for a in active])
        self.feature = np.asarray([x for a in active for x in a], dtype=int)
        self.text = np.asarray([n.tag == "#text" for n in keep])
        depth = np.zeros(len(keep), int)
        for k, p in enumerate(parent):
            depth[k] = depth[p] + 1 if p >= 0 else 0
        order = np.argsort(depth, kind="stable")
        self.levels = np.split(order, np.flatnonzero(np.diff(depth[order])) + 1) if len(order) else []

    def marginals(self, weights: np.ndarray, pair: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each node's probability of content, and each node's joint table with its parent (parent, child)."""
        own = np.zeros((len(self.nodes), 2))
        own[:, 1] = np.bincount(self.owner, weights[self.feature], len(self.nodes))
        edge = pair[self.text.astype(int)]  # node, parent, child
        up = own.copy()  # own potential and what the children say
        say = np.zeros((len(self.nodes), 2))  # to the parent
        for level in self.levels[:0:-1]:
            t = edge[level] + up[level][:, None, :]
            say[level] = np.logaddexp(t[:, :, 0], t[:, :, 1])
            np.add.at(up, self.parent[level], say[level])
        down = np.zeros((len(self.nodes), 2))
        joint = np.zeros((len(self.nodes), 2, 2))
        for level in self.levels[1:]:
            p = self.parent[level]
            rest = up[p] + down[p] - say[level]  # of the parent without this child
            t = edge[level] + rest[:, :, None]
            down[level] = np.logaddexp(t[:, 0, :], t[:, 1, :])
            both = t + up[level][:, None, :]
            both = np.exp(both - both.max((1, 2), keepdims=True))
            joint[level] = both / both.sum((1, 2), keepdims=True)
        belief = up + down
        return 1 / (1 + np.exp(np.clip(belief[:, 0] - belief[:, 1], -500, 500))), joint


def train(pages: list[str], steps: int = 150, rate: float = 0.15, ridge: float = 2e-4) -> tuple[np.ndarray, np.ndarray]:
    """Weights and parent-child tables from pages whose elements carry ``MARK`` = 0 or 1; a run has its element's label."""
    forest = Forest([parse(p) for p in pages])
    y = np.zeros(len(forest.nodes))
    for k, n in enumerate(forest.nodes):
        y[k] = float(n.attrs[MARK]) if MARK in n.attrs else y[forest.parent[k]] if forest.parent[k] >= 0 else 1.0
    weights, pair = np.zeros(len(_FEATURES)), np.zeros((2, 2, 2))
    kid = np.flatnonzero(forest.parent >= 0)
    seen = np.zeros((len(y), 2, 2))
    seen[kid, y[forest.parent[kid]].astype(int), y[kid].astype(int)] = 1
    mean, square = [np.zeros_like(weights), np.zeros_like(pair)], [np.zeros_like(weights), np.zeros_like(pair)]
    for step in range(1, steps + 1):
        p, joint = forest.marginals(weights, pair)
        off = seen - joint
        grad = [np.bincount(forest.feature, (y - p)[forest.owner], len(weights)), np.stack([off[kid][forest.text[kid] == t].sum(0) for t in (False, True)])]
        for k, x in enumerate((weights, pair)):
            g = grad[k] / len(pages) - ridge * x
            mean[k] = 0.9 * mean[k] + 0.1 * g
            square[k] = 0.99 * square[k] + 0.01 * g * g
            x += rate * (mean[k] / (1 - 0.9**step)) / (np.sqrt(square[k] / (1 - 0.99**step)) + 1e-8)
    return weights, pair


@lru_cache(1)
def trained(n: int = TRAIN_PAGES) -> tuple[np.ndarray, np.ndarray]:
    return train(labelled_pages(n))


def page_texts(pages: list[str | None], weights: np.ndarray, pair: np.ndarray) -> list[str]:
    forest = Forest([parse(p or "") for p in pages])
    p, _ = forest.marginals(weights, pair)
    take = forest.text & (p >= 0.5)
    return [" ".join(forest.nodes[k].text for k in range(a, b) if take[k]) for a, b in zip(forest.first[:-1], forest.first[1:], strict=True)]


def extract(pages: DataFrame, model: tuple[np.ndarray, np.ndarray] | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages(page_id, url, html)``."""
    weights, pair = model or trained()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                b = whole.slice(at, 64)
                texts = page_texts(b.column(2).to_pylist(), weights, pair)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
