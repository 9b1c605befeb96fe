"""Main text of HTML pages by a tree-structured graphical model.

Every DOM element has a hidden label, content or not. A node potential comes from a logistic model over the
element's tag, the words of its class and id, its share of link text, its text length and its place; an
edge potential joins the labels of parent and child. Sum-product messages go up the tree from the leaves
and down again from the root, level by level for all pages of a batch at once, and give each element's
exact marginal. A text run is kept when the element that holds it is more likely content than not.

Both potentials are trained from labelled pages: ``labelled_pages`` makes pages of many layouts (article in
``article``, ``main`` or a named ``div``; menus, headers, footers, sidebars, notices, adverts, forms and
reader comments around and inside it) with the role of every element. Other labelled pages can be given.

Defined results: null and empty pages give an empty text; a page cut short ends all that is open; pages
without tags are content as a whole; very long pages are read whole; rows that repeat are read alike;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zlib
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, dom

FEATURES = 4096
#: Elements whose text is never page text, whatever the model says.
NEVER = frozenset("head button select option input textarea script style noscript iframe template svg math canvas audio video object map datalist".split())
_NAME = re.compile(r"[a-z]+")


def _slot(name: str) -> int:
    return zlib.crc32(name.encode()) % (FEATURES - 1) + 1


_slots: dict[str, list[int]] = {}


def _named(tag: str, hint: str) -> list[int]:
    """Features of an element by itself: its tag and the words of its class and id."""
    key = f"{tag} {hint}"
    found = _slots.get(key)
    if found is None:
        words = sorted(set(_NAME.findall(hint)))
        found = [0, _slot(f"tag:{tag}"), *(_slot(f"word:{w}") for w in words)]
        if len(_slots) < 50_000:
            _slots[key] = found
    return found


def describe(tree: dom.Tree) -> list[list[int]]:
    """Active features of every element of a page."""
    n = len(tree.tag)
    own, linked, stops = [0] * n, [0] * n, [0] * n
    for at, s, _ in tree.runs:
        k = len(s.strip())
        own[at] += k
        stops[at] += s.count(".") + s.count("。")
    inside = [t == "a" for t in tree.tag]
    for i in range(1, n):
        inside[i] = inside[i] or inside[tree.parent[i]]
        if inside[i]:
            linked[i] += own[i]
    total, links, points = own[:], linked[:], stops[:]
    for i in range(n - 1, 0, -1):
        p = tree.parent[i]
        total[p] += total[i]
        links[p] += links[i]
        points[p] += points[i]
    main = [False] * n
    out = []
    for i in range(n):
        t, tag, up = total[i], tree.tag[i], tree.parent[i]
        main[i] = up >= 0 and (main[up] or tree.tag[up] in ("article", "main"))
        part = -1 if not t else min(4, 5 * links[i] // t)
        size = min(6, t.bit_length() // 2)
        above = tree.tag[up] if up >= 0 else ""
        out.append([*_named(tag, tree.hint[i]), *_named(f"{above}>{tag} {int(main[i])}", ""), _slot(f"links:{part}"), _slot(f"size:{size}"), _slot(f"points:{min(3, points[i])}"), _slot(f"{tag}:links:{part}")])
    return out


@dataclass
class Potentials:
    weights: np.ndarray
    edge: np.ndarray  # log potentials, parent label x child label


def marginals(potentials: Potentials, trees: list[dom.Tree], features: list[list[list[int]]] | None = None) -> list[np.ndarray]:
    """Content marginals of the elements of every tree by sum-product over all trees at once."""
    features = features or [describe(t) for t in trees]
    flat = [f for page in features for f in page]
    counts = np.array([len(f) for f in flat])
    ends = np.concatenate([[0], np.cumsum(counts)])
    score = np.add.reduceat(potentials.weights[np.concatenate([np.array(f) for f in flat])], ends[:-1])
    forest = Forest(trees)
    p, _ = forest.beliefs(score, potentials.edge)
    return [p[a:b] for a, b in zip(forest.base[:-1], forest.base[1:])]


class Forest:
    """All elements of some trees side by side, by level of depth."""

    def __init__(self, trees: list[dom.Tree]) -> None:
        self.base = np.concatenate([[0], np.cumsum([len(t.tag) for t in trees])])
        depths: list[int] = []
        for t in trees:  # parents stand before their children
            own = [0] * len(t.parent)
            for i in range(1, len(own)):
                own[i] = own[t.parent[i]] + 1
            depths += own
        self.parent = np.concatenate([np.where(np.array(t.parent) < 0, -1, np.array(t.parent) + b) for t, b in zip(trees, self.base)])
        depth = np.array(depths)
        order = np.argsort(depth, kind="stable")
        self.levels = np.split(order, np.flatnonzero(np.diff(depth[order])) + 1)

    def beliefs(self, score: np.ndarray, edge: np.ndarray, pairs: bool = False) -> tuple[np.ndarray, np.ndarray | None]:
        """Content marginals of all elements by messages up and down; with ``pairs`` also the summed marginals of parent and child."""
        node = np.stack([-score / 2, score / 2], 1)
        up, down, sent = node.copy(), np.zeros_like(node), np.zeros_like(node)
        for level in reversed(self.levels[1:]):
            m = np.logaddexp(edge[:, 0][None, :] + up[level, 0:1], edge[:, 1][None, :] + up[level, 1:2])
            m -= m.max(1, keepdims=True)
            sent[level] = m
            np.add.at(up, self.parent[level], m)
        both = np.zeros((2, 2)) if pairs else None
        for level in self.levels[1:]:
            p = self.parent[level]
            rest = up[p] + down[p] - sent[level]
            m = np.logaddexp(edge[0][None, :] + rest[:, 0:1], edge[1][None, :] + rest[:, 1:2])
            down[level] = m - m.max(1, keepdims=True)
            if pairs:
                joint = rest[:, :, None] + edge[None] + up[level][:, None, :]
                joint = np.exp(joint - joint.max((1, 2), keepdims=True))
                both += (joint / joint.sum((1, 2), keepdims=True)).sum(0)
        belief = up + down
        return 1 / (1 + np.exp(np.clip(belief[:, 0] - belief[:, 1], -50, 50))), both


def train(pages: list[tuple[dom.Tree, np.ndarray]], alone: int = 300, rounds: int = 120, rate: float = 0.3, decay: float = 1e-5) -> Potentials:
    """Potentials from labelled trees, by gradient ascent on the log-likelihood of all labels of a tree together.

    The gradient of a feature is its count among content elements less the count that sum-product expects, that
    of an edge potential the number of such parents and children less the expected one. Rounds in which elements stand
    ``alone``, without edges, find where to begin.
    """
    forest = Forest([tree for tree, _ in pages])
    rows, cols, n = [], [], 0
    for tree, label in pages:
        for i, f in enumerate(describe(tree)):
            rows += [n + i] * len(f)
            cols += f
        n += len(label)
    rows, cols, y = np.array(rows), np.array(cols), np.concatenate([label for _, label in pages])
    kids = np.flatnonzero(forest.parent >= 0)
    seen = np.bincount(y[forest.parent[kids]] * 2 + y[kids], minlength=4).reshape(2, 2)
    w, edge = np.zeros(FEATURES), np.zeros((2, 2))
    grad_w, grad_e = np.full(FEATURES, 1e-8), np.full((2, 2), 1e-8)
    for turn in range(alone + rounds):
        score = np.bincount(rows, w[cols], n)
        if turn < alone:
            p, step = 1 / (1 + np.exp(-np.clip(score, -30, 30))), 1.0
        else:
            (p, both), step = forest.beliefs(score, edge, True), rate
            g = (seen - both) / len(y)
            grad_e += g * g
            edge += step * g / np.sqrt(grad_e)
        g = np.bincount(cols, (y - p)[rows], FEATURES) / len(y) - decay * w
        grad_w += g * g
        w += step * g / np.sqrt(grad_w)
    return Potentials(w, edge - edge.mean())


def labelled_pages(n: int = 600, seed: int = 5) -> list[tuple[dom.Tree, np.ndarray]]:
    """Pages of varied layouts with a label for every element; the marker attribute that carries the label is not a feature."""
    rng = random.Random(seed)
    letters = "bcdfghklmnprstvw"

    def words(k: int) -> str:
        return " ".join("".join(rng.choice(letters) + rng.choice("aeiou") for _ in range(rng.randint(1, 4))) for _ in range(k))

    def sentence(lo: int = 6, hi: int = 25) -> str:
        return words(rng.randint(lo, hi)).capitalize() + rng.choice("..!?.")

    def links(k: int) -> str:
        return "".join(f'<li><a href="/{i}">{words(rng.randint(1, 3))}</a></li>' for i in range(k))

    def named(tag: str, *names: str) -> str:
        name = rng.choice(names)
        kind = rng.choice(["class", "class", "id"])
        return f'<{tag} {kind}="{name}">'

    def off(inner: str, tag: str, *names: str) -> str:
        return (named(tag, *names) if names else f"<{tag}>").replace(f"<{tag}", f"<{tag} data-off", 1) + inner + f"</{tag}>"

    def paragraphs(k: int) -> str:
        out = []
        for _ in range(k):
            s = " ".join(sentence() for _ in range(rng.randint(1, 6)))
            r = rng.random()
            if r < 0.15:
                at = s.split(" ")
                i = rng.randrange(len(at))
                at[i] = rng.choice(["<a href='x'>{}</a>", "<b>{}</b>", "<em>{}</em>", "<code>{}</code>"]).format(at[i])
                s = " ".join(at)
            out.append(rng.choice([f"<p>{s}</p>"] * 9 + [f"<p>{s}", f"<blockquote><p>{s}</p></blockquote>", f"<ul><li>{s}</li><li>{sentence()}</li></ul>", f"<h2>{words(rng.randint(1, 6))}</h2><p>{s}</p>", f"<table><tr><td>{words(2)}</td><td>{words(2)}</td></tr></table>", f"<pre>{s}</pre>", f"<div>{s}</div>", f"<figure><img src=x><figcaption>{sentence()}</figcaption></figure>", f"<b>{words(4)}<br><p>{s}</p>", f"<p>{words(1)}.</p>", f"<section><h3>{words(3)}</h3><p>{s}</p></section>"]))
        return "".join(out)

    def furniture() -> str:
        return rng.choice([
            lambda: off(f"<ul>{links(rng.randint(2, 9))}</ul>", "nav", *([] if rng.random() < 0.5 else ["menu", "navbar", "main-nav", "breadcrumb", "pagination"])),
            lambda: off(f"<ul>{links(rng.randint(2, 9))}</ul>", "div", "menu", "nav", "navigation", "topnav", "breadcrumbs", "pager", "toc", "tags", "share-links", "social"),
            lambda: off(f"<h1>{words(2)}</h1><p>{words(4)}</p>", rng.choice(["header", "header"]), *([] if rng.random() < 0.5 else ["site-header", "masthead", "banner", "top"])),
            lambda: off(f"<span>{words(2)}</span>", "div", "header", "masthead", "logo", "banner", "topbar"),
            lambda: off(" ".join(sentence(2, 30) for _ in range(rng.randint(1, 4))), "div", "ad", "ads", "advert", "advertisement", "sponsor", "sponsored", "promo", "promotion", "banner-ad", "ad-slot"),
            lambda: off(f"<h3>{words(2)}</h3>" * (rng.random() < 0.4) + f"<p>{sentence()}</p><a href=x>{words(1)}</a>", rng.choice(["aside", "div", "section"]), "ad", "promo", "sponsored", "newsletter", "subscribe", "related", "recommended", "widget", "sidebar"),
            lambda: off(f"<h3>{words(2)}</h3><ul>{links(rng.randint(2, 6))}</ul><p>{sentence()}</p>", "aside", *([] if rng.random() < 0.5 else ["sidebar", "side", "related", "widget"])),
            lambda: off(f"<h4>{words(2)}</h4>{links(3)}<p>{sentence()}</p>", "div", "sidebar", "widget", "related-posts", "side-col", "rail"),
            lambda: off(f"<p>{sentence()}</p><button>{words(1)}</button>", "div", "cookie", "cookie-notice", "notice", "consent", "gdpr", "alert", "modal", "popup", "overlay", "paywall", "disclaimer"),
            lambda: off(f"<label>{words(2)}</label><input name=q><textarea></textarea><button>{words(1)}</button>", "form", *([] if rng.random() < 0.5 else ["search", "login", "subscribe", "contact"])),
            lambda: off(f"<h{rng.randint(2, 4)}>{words(rng.randint(1, 3))}</h2>" * (rng.random() < 0.6) + "".join(f'<div class="comment"><b>{words(1)}</b><p>{sentence()} {sentence()}</p></div>' for _ in range(rng.randint(1, 5))), rng.choice(["div", "section", "ol"]), "comments", "comment-list", "responses", "discussion", "reader-comments", "replies", "disqus_thread"),
            lambda: off(f"<h2>{words(2)}</h2><article data-off class=\"comment\"><p>{sentence()} {sentence()}</p></article>", "section", "comments", "user-comments"),
            lambda: off(f"&copy; {words(2)} &middot; {sentence(2, 12)}", "footer", *([] if rng.random() < 0.6 else ["site-footer", "footer", "colophon"])),
            lambda: off(f"<p>{sentence(3, 12)}</p><ul>{links(4)}</ul>", "div", "footer", "site-footer", "legal", "copyright", "bottom"),
        ])()

    def article() -> str:
        inner = f"<h1>{words(rng.randint(1, 9))}</h1>" * (rng.random() < 0.85) + paragraphs(rng.randint(0, 14))
        if rng.random() < 0.35:
            inner += furniture()
            inner += paragraphs(rng.randint(0, 4))
        if rng.random() < 0.15:
            inner = f"<header><h1>{words(4)}</h1></header>" + inner
        shape = rng.random()
        if shape < 0.45:
            return f"<article>{inner}</article>"
        if shape < 0.6:
            return f"<main>{inner}</main>"
        if shape < 0.7:
            return f"<main><article>{inner}</article></main>"
        name = rng.choice(["content", "article", "post", "entry-content", "story", "main-content", "article-body", "text", "post-body"])
        return f"<div class='{name}'>{inner}</div>" if shape < 0.92 else f"<div id='{name}'><div>{inner}</div></div>"

    pages = []
    for _ in range(n):
        top, bottom = "".join(furniture() for _ in range(rng.randint(0, 4))), "".join(furniture() for _ in range(rng.randint(0, 4)))
        body = top + article() + bottom
        if rng.random() < 0.3:
            body = f'<div class="{rng.choice(["page", "wrapper", "container", "site", "layout"])}">{body}</div>'
        page = f"<html><head><title>{words(3)}</title><style>p{{}}</style></head><body>{body}</body></html>"
        page = page.replace("<p>", "<p> ")
        marked = re.sub(r"<(\w+) data-off((?: \w+=\"[^\"]*\")?)>", lambda m: f"<{m[1]}{m[2][:-1] + ' zzoff' + chr(34) if m[2] else ' class=' + chr(34) + 'zzoff' + chr(34)}>", page)
        tree = dom.parse(marked)
        label = np.zeros(len(tree.tag), np.int64)
        dropped = [False] * len(tree.tag)
        for i, t in enumerate(tree.tag):
            up = tree.parent[i]
            dropped[i] = (up >= 0 and dropped[up]) or "zzoff" in tree.hint[i] or t in NEVER
            label[i] = not dropped[i]
        for i in range(len(tree.tag)):
            tree.hint[i] = tree.hint[i].replace("zzoff", "")
        pages.append((tree, label))
    return pages


_trained: Potentials | None = None


def default_potentials() -> Potentials:
    """Potentials of the built-in labelled pages, trained once a process."""
    global _trained
    if _trained is None:
        _trained = train(labelled_pages())
    return _trained


_SPACES = re.compile(r"\s+")


def render(tree: dom.Tree, p: np.ndarray, level: float = 0.5) -> str:
    """Kept runs: white space is one space, runs of a block are joined as they stand, blocks by one space."""
    keep = (p > level).tolist()
    never = [t in NEVER for t in tree.tag]
    for i in range(1, len(never)):
        up = tree.parent[i]
        never[i] = never[i] or never[up]
        if tree.tag[i] in dom.INLINE_OPEN and not tree.hint[i]:
            keep[i] = keep[up]  # unnamed inline elements go with their block
    blocks: list[str] = []
    own: list[str] = []
    for at, s, fresh in tree.runs:
        if fresh and own:
            blocks.append("".join(own))
            own = []
        if keep[at] and not never[at]:
            own.append(s)
    blocks.append("".join(own))
    return " ".join(b for b in (_SPACES.sub(" ", x).strip() for x in blocks) if b)


def _extractor(potentials: Potentials):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(2)
            texts: list[str] = []
            for lo in range(0, batch.num_rows, 256):
                some = [h.decode("utf-8", "replace") for h in common.byte_rows(column.slice(lo, 256))]
                trees = [dom.parse(h) for h in some]
                texts += [render(t, p) for t, p in zip(trees, marginals(potentials, trees))] if trees else []
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return run


def extract(pages: DataFrame, key: str = "page_id", url: str = "url", page: str = "html", potentials: Potentials | None = None) -> DataFrame:
    """One row per page: key, url, text, n_chars."""
    rows = pages.select(F.col(key).alias("k"), F.col(url).cast("string").alias("u"), F.col(page).cast("string").alias("h"))
    kind = rows.schema["k"].dataType.simpleString()
    out = rows.mapInArrow(_extractor(potentials or default_potentials()), f"page_id {kind}, url string, text string, n_chars long")
    return out.select(F.col("page_id").alias(key), F.col("url").alias(url), "text", "n_chars")


def op5_html_extraction(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
