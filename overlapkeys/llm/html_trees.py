"""Operator 7: main text of HTML by gradient-boosted trees over DOM nodes.

A tolerant scanner builds a tree of block nodes. Trees boosted on a small labelled set of pages, which a
rule builds here, give each node's probability of being main content. Decoding is hierarchical: a
subtree is taken whole, left whole, or decided child by child, whichever is likeliest, so a node's
text never contradicts the choice for an ancestor.
"""

from __future__ import annotations

import html as entities
import random
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from .common import filled_id, unfilled

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style)\b[^>]*>.*?(?:</\1\s*>|\Z)|<(noscript|template|svg|textarea|title)(?=[\s/>])[^>]*(?<!/)>.*?</\2\s*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?/][^>]*>|<[a-zA-Z!?/][^>]*\Z", re.S | re.I)
SPACE = re.compile(r"\s+")
ATTRIBUTE = re.compile(r"(?:class|id|role|aria-label)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
PART = re.compile(r"[a-z]+")
# HTML's block elements, void elements, and tokens of class and id attributes.
BLOCK = frozenset("address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html iframe label legend li main menu nav ol option p pre search section select summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
ENDS_P = BLOCK - {"button", "label", "option", "select"}
AGAINST = frozenset("ad ads advert advertisement advertorial banner sponsor sponsored promo promoted menu nav navbar navigation sidebar aside rail widget footer foot header masthead topbar cookie consent notice alert popup modal overlay newsletter subscribe signup login comment comments disqus reply respond discussion share sharing social related recommended breadcrumb breadcrumbs pagination pager tags toolbar search form copyright legal skip disclaimer gdpr paywall trending popular".split())
FOR = frozenset("article content post entry main story body text page hentry prose bodytext paragraph".split())
NESTED = {"li": {"ul", "ol", "menu", "dir"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "tr": {"table", "tbody", "thead", "tfoot"}, "dd": {"dl"}, "dt": {"dl"}, "option": {"select"}}
KIND = {t: k + 1 for k, ts in enumerate(["nav menu", "header", "footer", "aside", "form button select label option fieldset", "article main", "section div", "p blockquote pre", "h1 h2 h3 h4 h5 h6", "li ul ol dl dd dt", "table tr td th tbody"]) for t in ts.split()}


class Node:
    __slots__ = ("tag", "up", "kids", "good", "bad", "runs", "chars", "linked", "paras", "nodes", "commas", "depth", "at", "links")

    def __init__(self, tag: str, up: Node | None, attributes: str):
        self.tag, self.up, self.kids, self.runs = tag, up, [], []
        self.good = self.bad = 0
        if attributes:
            for m in ATTRIBUTE.finditer(attributes):
                parts = PART.findall(m[1].lower())
                self.good += sum(p in FOR for p in parts)
                self.bad += sum(p in AGAINST for p in parts)
        self.chars = self.linked = self.paras = self.commas = self.links = 0
        self.nodes, self.depth = 1, up.depth + 1 if up else 0
        self.at = len(up.kids) if up else 0


def parse(page: str) -> tuple[Node, list[tuple[Node, str]]]:
    """The tree of block nodes and the blocks (node, text) in page order.

    A block is the text between two block-level tags: inline tags don't part it, a line break is white space.
    """
    root = Node("#", None, "")
    node, blocks, buffer, in_link, stack = root, [], [], 0, [root]
    open_tags: Counter[str] = Counter()  # on the stack, so that a tag without a partner costs no search

    def close_from(k: int) -> None:
        open_tags.subtract(n.tag for n in stack[k:])
        del stack[k:]

    def flush() -> None:
        if buffer:
            text = SPACE.sub(" ", entities.unescape("".join(b for b, _ in buffer))).strip()
            if text:
                blocks.append((node, text))
                node.runs.append(text)
                node.chars += len(text)
                node.linked += sum(len(b) for b, linked in buffer if linked)
                node.commas += text.count(",") + text.count(".")
            buffer.clear()

    at = 0
    for m in TOKEN.finditer(page):
        if m.start() > at:
            buffer.append((page[at : m.start()], in_link > 0))
        at = m.end()
        name = m[4]
        if name is None:
            continue
        name, closing = name.lower(), m[3] == "/"
        if name == "a":
            in_link = max(0, in_link - 1) if closing else 1
            node.links += not closing
            continue
        if name == "br":
            buffer.append((" ", False))
            continue
        if name not in BLOCK:
            continue
        flush()
        if closing:
            if open_tags[name]:
                close_from(next(k for k in range(len(stack) - 1, 0, -1) if stack[k].tag == name))
        else:
            if name in ENDS_P and stack[-1].tag == "p":
                close_from(len(stack) - 1)
            if name in NESTED and open_tags[name]:
                k = next(k for k in range(len(stack) - 1, 0, -1) if stack[k].tag == name or stack[k].tag in NESTED[name])
                if stack[k].tag == name:
                    close_from(k)
            if name not in VOID and not m[5].endswith("/"):
                new = Node(name, stack[-1], m[5])
                stack[-1].kids.append(new)
                stack.append(new)
                open_tags[name] += 1
        node = stack[-1]
        in_link = 0
    if at < len(page):
        buffer.append((page[at:], in_link > 0))
    flush()
    return root, blocks


FEATURES = 26


def features(root: Node) -> tuple[list[Node], np.ndarray]:
    """Nodes, parents before children, and a row of features for each."""
    order = [root]
    for n in order:
        order.extend(n.kids)
    own = [(n.chars, n.linked) for n in order]
    for n in reversed(order):
        n.paras += n.tag in ("p", "blockquote", "pre")
        if n.up is not None:
            u = n.up
            u.chars += n.chars
            u.linked += n.linked
            u.paras += n.paras
            u.nodes += n.nodes
            u.commas += n.commas
            u.links += n.links
    total = max(1, root.chars)
    x = np.zeros((len(order), FEATURES), np.float32)
    above: dict[int, tuple] = {id(None): (0, 0, 0, 0, 0, 0)}
    for k, (n, (chars, linked)) in enumerate(zip(order, own)):
        kind = KIND.get(n.tag, 0)
        good, bad, shut, open_, li, cousins = above[id(n.up)]
        u = n.up
        around = (u.chars - n.chars) / max(1, len(u.kids) - 1) if u is not None and len(u.kids) > 1 else 0.0
        mean = n.chars / n.nodes
        x[k] = (
            kind, chars, n.chars, n.chars / total, n.linked / max(1, n.chars), linked / max(1, chars), n.paras, mean, n.commas / max(1, n.chars), n.depth, n.at, n.at / max(1, len(u.kids) - 1) if u is not None else 0, len(u.kids) if u is not None else 1,
            around, n.good, n.bad, good, bad, shut, open_, li, KIND.get(u.tag, 0) if u is not None else 0, u.linked / max(1, u.chars) if u is not None else 0, u.paras if u is not None else 0, n.links, cousins,
        )
        above[id(n)] = (good + n.good, bad + n.bad, shut + (1 <= kind <= 5), open_ + (kind == 6), li + (kind == 10), n.paras)
    return order, x


class BoostedTrees:
    """Logistic gradient boosting with trees of a fixed depth over binned features."""

    def __init__(self, depth: int = 4, rounds: int = 60, rate: float = 0.2, bins: int = 32):
        self.depth, self.rounds, self.rate, self.bins = depth, rounds, rate, bins
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> BoostedTrees:
        cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins)[1:-1])) for j in range(x.shape[1])]
        binned = np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(cuts)], 1)
        raw = np.zeros(len(x))
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-raw))
            g, h = (y - p) * weight, np.maximum(p * (1 - p), 1e-6) * weight
            n_inner = 2**self.depth - 1
            col, cut = np.zeros(n_inner, np.int64), np.full(n_inner, np.inf)
            leaf = np.zeros(len(x), np.int64)  # position in the heap of nodes
            for at in range(n_inner):
                rows = np.flatnonzero(leaf == at)
                best = (1e-9, 0, np.inf, self.bins)
                G, H = g[rows].sum(), h[rows].sum()
                for j in range(x.shape[1]):
                    if not len(cuts[j]) or len(rows) < 8:
                        continue
                    gl = np.cumsum(np.bincount(binned[rows, j], g[rows], len(cuts[j]) + 1))[:-1]
                    hl = np.cumsum(np.bincount(binned[rows, j], h[rows], len(cuts[j]) + 1))[:-1]
                    gain = gl**2 / (hl + 1) + (G - gl) ** 2 / (H - hl + 1) - G**2 / (H + 1)
                    k = int(gain.argmax())
                    if gain[k] > best[0]:
                        best = (gain[k], j, cuts[j][k], k)
                col[at], cut[at] = best[1], best[2]
                leaf[rows] = 2 * at + 1 + (binned[rows, best[1]] > best[3])
            leaf -= n_inner
            size = n_inner + 1
            value = np.bincount(leaf, g, size) / (np.bincount(leaf, h, size) + 1) * self.rate
            self.trees.append((col, cut, value))
            raw += value[leaf]
        return self

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        raw = np.zeros(len(x))
        rows = np.arange(len(x))
        for col, cut, value in self.trees:
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                at = 2 * at + 1 + (x[rows, col[at]] >= cut[at])
            raw += value[at - len(col)]
        return raw


def labelled_pages(n: int = 420, seed: int = 11) -> Iterator[tuple[str, set[str]]]:
    """Small training set built by rule: (page, its main blocks), with many kinds of frames around the article."""
    r = random.Random(seed)
    made = 0

    def words(lo: int, hi: int) -> str:
        nonlocal made
        made += 1
        run = ["".join(r.choice("abcdefghilmnoprstuvé") for _ in range(r.randint(2, 9))) + ("," if r.random() < 0.08 else "") for _ in range(r.randint(lo, hi))]
        return " ".join([*run[:-1], f"{run[-1]}{made}" + r.choice(["", ".", ".", "."])])

    pick = r.choice
    link = lambda: f'<a href="/{made}">{words(1, 3)}</a>'
    menu = lambda: "<ul>" + "".join(f"<li>{link()}</li>" for _ in range(r.randint(3, 9))) + "</ul>"
    para = lambda lo=4, hi=40: f"<p>{words(lo, hi)}</p>"
    frames = [
        lambda: f"<nav>{menu()}</nav>", lambda: f'<div class="{pick(["menu", "navbar", "main-nav", "breadcrumbs"])}">{menu()}</div>', lambda: f'<header class="site-header"><h1>{words(1, 4)}</h1>{pick(["", menu(), para(3, 9)])}</header>',
        lambda: f"<header><div>{link()}</div><p>{words(2, 9)}</p></header>", lambda: f'<div class="{pick(["ad", "ads", "advert", "banner", "sponsored", "promo"])}">{pick([words(3, 20), para(3, 20), para() + link()])}</div>',
        lambda: f'<div id="{pick(["cookie-notice", "consent", "notice", "gdpr-banner"])}"><p>{words(6, 30)}</p><button>{words(1, 2)}</button></div>', lambda: f"<form>{para(2, 6)}<label>{words(1, 3)}</label><select><option>{words(1, 2)}</option></select><button>{words(1, 2)}</button></form>",
        lambda: f'<div class="{pick(["newsletter", "signup", "login"])}"><p>{words(4, 15)}</p><form><button>{words(1, 2)}</button></form></div>', lambda: f"<aside>{pick([menu(), para(5, 40), '<h3>' + words(1, 4) + '</h3>' + para(4, 30)])}</aside>",
        lambda: f'<div class="{pick(["sidebar", "related", "widget", "popular-posts", "share"])}"><h3>{words(1, 3)}</h3>{pick([menu(), para(4, 25)])}</div>', lambda: f"<footer>{pick([words(3, 15), para(3, 15), menu() + para(3, 12)])}</footer>", lambda: f'<div class="footer">&copy; {words(2, 12)}</div>',
        lambda: f'<{(t := pick(["section", "div"]))} {pick(["class", "id"])}="{pick(["comments", "comment-list", "discussion", "respond"])}"><h3>{words(1, 3)}</h3>' + "".join(f'<div class="{pick(["comment", "reply", "x"])}">{para(3, 40)}</div>' for _ in range(r.randint(1, 6))) + f"</{t}>",
    ]
    for _ in range(n):
        gold: set[str] = set()

        def keep(text: str, gold: set[str] = gold) -> str:
            gold.add(SPACE.sub(" ", entities.unescape(re.sub(r"<[^>]*>", "", text))).strip())
            return text

        body = [f"<{(h := pick(['h1', 'h2']))}>{keep(words(2, 12))}</{h}>"] if r.random() < 0.8 else []
        for _ in range(r.randint(1, 12)):
            kind = r.random()
            if kind < 0.72:
                body.append(pick(["<p>{}</p>", "<p>{}</p>", "<p>{}", "<p><b>{}<br></p>", "<p class='x'>{}</p>"]).format(keep(words(1, 60))))
            elif kind < 0.8:
                body.append(f"<h3>{keep(words(1, 6))}</h3>")
            elif kind < 0.88:
                body.append("<ul>" + "".join(f"<li>{keep(words(2, 14))}</li>" for _ in range(r.randint(2, 5))) + "</ul>")
            elif kind < 0.93:
                body.append(f"<blockquote>{keep(words(4, 30))}</blockquote>")
            elif kind < 0.96:
                body.append("<table><tr>" + "".join(f"<td>{keep(words(1, 4))}</td>" for _ in range(3)) + "</tr></table>")
            else:
                body.append(pick(frames[4:10])())  # an advert or widget inside
        tag, attribute = pick([("article", ""), ("article", ""), ("main", ""), ("div", ' class="content"'), ("div", ' class="post-body entry"'), ("div", ' id="article"'), ("section", ' class="story"'), ("div", ""), ("td", "")])
        before = "".join(pick(frames[:10])() for _ in range(r.randint(0, 4)))
        after = "".join(pick(frames[4:])() for _ in range(r.randint(0, 4)))
        wrap = pick(["{}", "{}", "<div>{}</div>", '<div id="page"><div class="wrap">{}</div></div>', "<main>{}</main>"])
        whole = before + wrap.format(f"<{tag}{attribute}>{''.join(body)}</{tag}>") + after
        if r.random() < 0.3:
            whole = wrap.format(whole)
        yield f"<!DOCTYPE html><html><head><title>{words(2, 9)}</title></head><body>{whole}</body></html>", gold


@lru_cache(1)
def trained_trees() -> BoostedTrees:
    xs, ys, ws = [], [], []
    for page, gold in labelled_pages():
        root, blocks = parse(page)
        order, x = features(root)
        main, every = dict.fromkeys(map(id, order), 0), dict.fromkeys(map(id, order), 0)
        for node, text in blocks:
            while node is not None:
                every[id(node)] += len(text)
                main[id(node)] += len(text) * (text in gold)
                node = node.up
        for k, n in enumerate(order):
            if every[id(n)]:
                xs.append(x[k])
                ys.append(main[id(n)] / every[id(n)])
                ws.append(1.0)
    return BoostedTrees().fit(np.array(xs), np.array(ys), np.array(ws))


def main_blocks(order: list[Node], odds: np.ndarray) -> set[int]:
    """ids of the nodes whose own text is main, by the likeliest consistent choice."""
    yes = -np.logaddexp(0, -odds)
    no = -np.logaddexp(0, odds)
    at = {id(n): k for k, n in enumerate(order)}
    whole, none, mixed = yes.copy(), no.copy(), np.zeros(len(order))
    own = np.array([bool(n.runs) for n in order])
    mixed += np.where(own, np.maximum(yes, no), 0.0)
    whole = np.where(own, yes, 0.3 * yes)
    none = np.where(own, no, 0.3 * no)
    best = np.zeros(len(order))
    for k in range(len(order) - 1, -1, -1):
        if order[k].kids:
            mixed[k] += -0.7  # a split has its price, so siblings tend to go together
        else:
            mixed[k] = -np.inf
        best[k] = max(whole[k], none[k], mixed[k])
        if k:
            u = at[id(order[k].up)]
            whole[u] += whole[k]
            none[u] += none[k]
            mixed[u] += best[k]
    chosen: set[int] = set()
    todo = [(0, "")]
    while todo:
        k, choice = todo.pop()
        n = order[k]
        if not choice:
            choice = "in" if whole[k] >= max(none[k], mixed[k]) else "out" if none[k] >= mixed[k] else "split"
        if choice == "in" or choice == "split" and own[k] and odds[k] > 0:
            chosen.add(id(n))
        todo += [(at[id(c)], "" if choice == "split" else choice) for c in n.kids]
    return chosen


def extract(pages: list[str], trees: BoostedTrees) -> list[str]:
    parsed = [parse(p) for p in pages]
    found = [features(root) for root, _ in parsed]
    odds = trees.log_odds(np.concatenate([x for _, x in found])) if found else np.zeros(0)
    out, at = [], 0
    for (_, blocks), (order, _) in zip(parsed, found):
        chosen = main_blocks(order, odds[at : at + len(order)])
        at += len(order)
        out.append("\n".join(text for node, text in blocks if id(node) in chosen))
    return out


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for each row; a null or empty page gives an empty text. No shuffle.

    Rows are independent: repeated rows give repeated results, an empty table none, other columns may have
    any names. Nesting has no bound; a page's tree is held in a worker's memory while it is decided.
    """
    trees = trained_trees()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            html, text = f["html"].fillna("").tolist(), []
            for at in range(0, len(html), 200):
                text += extract(html[at : at + 200], trees)
            yield pd.DataFrame({"page_id": f["page_id"], "url": f["url"], "text": text, "n_chars": [len(t) for t in text]})

    return unfilled(pages.select(filled_id("page_id"), "url", "html").mapInPandas(run, "page_id long, url string, text string, n_chars long"), "page_id")


def op7_html_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
