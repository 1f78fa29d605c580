"""Main text of web pages: boosted trees score every DOM node, a tree decoder picks a consistent set of nodes.

Nodes are block elements and runs of inline text. Features: the tag and those above it, tokens of class, id, role and
itemprop (own and inherited), whether markup hides the node, depth, text and link density of the subtree, counts of
paragraphs, controls and punctuation, and sibling statistics. A token is hashed into a bucket, and a bucket counts by
the log odds that training nodes with it hold main text; no word list speaks for or against a node. Decoding maximises the summed log odds under one rule, that a kept node has kept
ancestors: the best choice of each subtree follows bottom-up from its children's.

The model is trained here, on pages that `Inventor` makes from random templates with known main text; their number and
seed are parameters. Scripts, styles, form controls, templates and the fallback texts of noscript and iframe are never
taken; everything else of the article stays, formulas, drawings' texts and hidden paragraphs too.

Edge cases: null or empty html gives an empty text; markup without any tag is one run; unclosed and crossed tags,
attributes and comments are read as far as they go; null page_id and url are passed on; repeated rows give equal rows;
very large pages are one page in memory; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import dom
from .boosting import Boosted
from .common import batches, pick

TRAINING_PAGES, SEED, CHUNK = 700, 20240, 100
MARK = "\ue000"
GROUPS = [("p",), ("h1",), ("h2", "h3", "h4", "h5", "h6"), ("li", "dt", "dd"), ("ul", "ol", "dl", "menu"), ("div", "center"), ("section",), ("article",), ("main",), ("nav", "search"), ("header", "hgroup"), ("footer", "address"), ("aside",), ("form", "fieldset", "legend"), ("table", "tbody", "tr", "td", "th", "thead", "tfoot", "caption"), ("figure", "figcaption", "blockquote", "pre", "details", "summary"), ("#run",), ("body", "html", "#root")]
_GROUP = {tag: i for i, tags in enumerate(GROUPS) for tag in tags}
_SPLIT = re.compile(r"[^A-Za-z]+|(?<=[a-z])(?=[A-Z])")
_STOPS = re.compile(r"[.!?,;:…。]")
#: Buckets of attribute tokens, what a bucket's odds are smoothed by, and odds that count as a sign.
BUCKETS, PRIOR, SIGN = 1 << 16, 2.0, 1.0


@lru_cache(maxsize=20_000)
def token_buckets(tokens: str) -> tuple[int, ...]:
    """Buckets of an element's attribute tokens: words between signs, digits and capitals."""
    return tuple({zlib.crc32(t.lower().encode()) % BUCKETS for t in _SPLIT.split(tokens) if t})


def token_odds(pages: list[list[dom.Node]]) -> dict[int, float]:
    """{bucket: log odds of main text below a node with a token of this bucket, against all such nodes}, smoothed."""
    main, every = Counter(), Counter()
    for nodes in pages:
        for x in nodes:
            if x.tokens:
                found = token_buckets(x.tokens)
                every.update(found)
                if x.y:
                    main.update(found)
    share = (sum(main.values()) + 1) / (sum(every.values()) + 2)
    return {b: math.log((main[b] + PRIOR * share) / (n - main[b] + PRIOR * (1 - share)) * (1 - share) / share) for b, n in every.items()}


def features(root: dom.Node, nodes: list[dom.Node], odds: dict[int, float]) -> np.ndarray:
    """One row of features for each node, in page order; parents come before children. odds: of token buckets."""
    n = len(nodes)
    place = {id(node): i for i, node in enumerate(nodes)}
    parent = [place[id(x.parent)] if x.parent else -1 for x in nodes]
    chars, linked, stops, runs, paras, controls, marks, elements, words = ([0] * n for _ in range(9))
    for i in range(n - 1, -1, -1):
        x = nodes[i]
        if x.tag == "#run":
            chars[i], linked[i], stops[i], runs[i], marks[i], words[i] = len(x.text), x.linked, len(_STOPS.findall(x.text)), 1, x.marks, x.text.count(" ") + 1
        else:
            controls[i] += x.controls
            elements[i] += 1
            paras[i] += x.tag == "p"
        j = parent[i]
        if j >= 0:
            for sums in (chars, linked, stops, runs, paras, controls, marks, elements, words):
                sums[j] += sums[i]
    total = max(1, chars[0])
    out = np.zeros((n, 21 + 6 + 2 * len(GROUPS)), np.float32)
    up: list[tuple] = [None] * n
    before = 0
    for i, x in enumerate(nodes):
        found = [odds.get(b, 0.0) for b in token_buckets(x.tokens)] if x.tokens else ()
        good, bad = max(found, default=0.0), min(found, default=0.0)
        group = _GROUP.get(x.tag, 5)
        if parent[i] >= 0:
            most, least, flags, near_good, near_bad = up[parent[i]]
        else:
            most, least, flags, near_good, near_bad = 0.0, 0.0, 0, 99, 99
        most, least = max(most, good), min(least, bad)
        near_good = 0 if good > SIGN else near_good + 1
        near_bad = 0 if bad < -SIGN else near_bad + 1
        up[i] = (most, least, flags | (1 << group), near_good, near_bad)
        siblings = x.parent.children if x.parent else [x]
        k = len(siblings)
        row = out[i]
        c = chars[i]
        row[:21] = (x.depth, c, words[i], linked[i] / max(1, c), stops[i] / max(1, words[i]), c / max(1, elements[i]), runs[i], paras[i], controls[i], marks[i] / max(1, words[i]), elements[i], c / total, before / total, good, bad, most, least, near_good, near_bad, x.text[:1].islower(), x.hidden)
        row[27 + group] = 1
        if x.parent:
            j = parent[i]
            row[21:27] = (k, c / max(1, chars[j]), chars[j] / k, linked[j] / max(1, chars[j]), paras[j], controls[j])
        base = 27 + len(GROUPS)
        for g in range(len(GROUPS)):
            row[base + g] = flags >> g & 1
        if x.tag == "#run":
            before += c
    return out


def decode(nodes: list[dom.Node], odds: np.ndarray) -> list[bool]:
    """Keep or drop each node: the most likely labelling in which every kept node's parent is kept."""
    place = {id(node): i for i, node in enumerate(nodes)}
    value = odds.astype(float).tolist()
    for i in range(len(nodes) - 1, 0, -1):
        if value[i] > 0:
            value[place[id(nodes[i].parent)]] += value[i]
    kept = [False] * len(nodes)
    for i, x in enumerate(nodes):
        kept[i] = value[i] > 0 and (x.parent is None or kept[place[id(x.parent)]])
    return kept


@dataclass
class Model:
    """Trees over features, and the odds of attribute tokens that are among those."""

    trees: Boosted
    tokens: dict[int, float]


def extract(pages: list[str], model: Model) -> list[str]:
    """The main text of each page: kept runs in page order, one line each."""
    parsed = [dom.parse(p or "") for p in pages]
    if not parsed:
        return []
    odds = model.trees.log_odds(np.concatenate([features(*p, model.tokens) for p in parsed]))
    out, at = [], 0
    for _, nodes in parsed:
        kept = decode(nodes, odds[at : at + len(nodes)])
        at += len(nodes)
        out.append("\n".join(x.text for x, k in zip(nodes, kept) if k and x.tag == "#run"))
    return out


# ---------------------------------------------------------------- training pages

_SYLLABLES = "the an er on in at re ou ea le la ier ment que ción ar os ñ é ü ch sch ung en ge be ti ha st and of to oi eau ie do".split()


class Inventor:
    """Random pages with known main text: each of its runs starts with MARK."""

    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def words(self, low: int, high: int) -> str:
        r = self.r
        out = []
        for _ in range(r.randint(low, high)):
            w = "".join(r.choice(_SYLLABLES) for _ in range(r.randint(1, 4)))
            out.append(w + (r.choice(".,") if r.random() < 0.15 else ""))
        text = " ".join(out).capitalize()
        if r.random() < 0.05:
            text = " ".join(w + r.choice(["$$$", "%%%", "!!", "###"]) for w in text.split())
        return text + r.choice([".", ".", ".", "", "!", "?"])

    def attrs(self, *tokens: str) -> str:
        r = self.r
        t = r.choice(tokens)
        if r.random() < 0.5:
            t = r.choice(["site", "page", "c", "js", "block", "the", "x", "my", "global"]) + r.choice("-_") + t
        if r.random() < 0.2:
            t += r.choice(["-1", "-wrap", "__inner", " clearfix", "-box", " row"])
        return f' {r.choice(["class", "class", "id", "role"])}="{t}"'

    def box(self, tags: str, tokens: str, inner: str, bare: float = 0.1) -> str:
        r = self.r
        tag = r.choice(tags.split())
        plain = tag in ("nav", "header", "footer", "aside", "form", "article", "main")
        attrs = "" if r.random() < (0.6 if plain else bare) else self.attrs(*tokens.split())
        if r.random() < 0.04:
            attrs += self.hide()
        return f"<{tag}{attrs}>{inner}</{tag}>"

    def hide(self) -> str:
        return self.r.choice([" hidden", ' aria-hidden="true"', ' style="display:none"'])

    def links(self, low: int = 2, high: int = 9) -> str:
        r = self.r
        items = [f'<a href="/{i}">{self.words(1, 3)}</a>' for i in range(r.randint(low, high))]
        if r.random() < 0.75:
            return "<ul>" + "".join(f"<li>{x}</li>" for x in items) + "</ul>"
        return r.choice([" | ", " ", " &middot; "]).join(items)

    def blurb(self) -> str:
        """Boilerplate prose of any shape."""
        r = self.r
        text = self.words(2, r.choice([6, 14, 40]))
        form = r.random()
        if form < 0.35:
            return text
        if form < 0.75:
            return "".join(f"<p>{self.words(2, r.choice([8, 25]))}</p>" for _ in range(r.randint(1, 3)))
        return f"<h{r.randint(2, 4)}>{self.words(1, 4)}</h{r.randint(2, 4)}><p>{text}</p>"

    def form(self) -> str:
        fields = "".join(f"<label>{self.words(1, 3)}</label><input name=x>" for _ in range(self.r.randint(1, 3)))
        head = self.r.choice(["", f"<h3>{self.words(1, 4)}</h3>", f"<p>{self.words(3, 15)}</p>"])
        return f"<form{self.r.choice(['', self.attrs('search', 'login', 'newsletter', 'subscribe', 'contact')])}>{head}{fields}<button>{self.words(1, 2)}</button></form>"

    def comments(self) -> str:
        r = self.r
        tag = r.choice(["li", "div", "article", "p"])
        one = lambda: f"<{tag}{self.attrs('comment', 'reply') if r.random() < 0.7 else ''}>" + r.choice(["", f"<span>{self.words(1, 2)}</span> ", f"<h4>{self.words(1, 2)}</h4>"]) + (self.words(3, 40) if tag == "p" else f"<p>{self.words(3, 40)}</p>") + f"</{tag}>"
        many = "".join(one() for _ in range(r.randint(1, 6)))
        if tag == "li":
            many = f"<ol>{many}</ol>"
        return self.box("section div div aside", "comments comment-list discussion disqus respond", r.choice(["", f"<h3>{self.words(1, 3)}</h3>"]) + many, bare=0)

    def clutter(self) -> str:
        r = self.r
        return r.choice([
            lambda: self.box("div div aside section ins", "ad ads advert advertisement banner sponsored promo", self.blurb(), bare=0),
            lambda: self.box("div div p section aside", "notice cookie cookie-notice alert announcement gdpr consent warning disclaimer message privacy", self.blurb(), bare=0),
            lambda: self.box("div section dialog", "modal popup paywall overlay subscription signup login", self.blurb() + r.choice(["", self.form()]), bare=0),
            lambda: self.box("div nav ul section", "pagination pager toc toolbar skip-links dropdown", self.links(2, 7), bare=0),
            lambda: self.box("div ul section", "share social sharing tags meta byline bio", self.links(2, 5), bare=0),
            lambda: self.box("div section aside", "related recommended trending feedback promoted", f"<h3>{self.words(1, 3)}</h3>" + self.links() + r.choice(["", f"<p>{self.words(3, 20)}</p>"]), bare=0),
            self.form,
        ])()

    def main(self) -> str:
        """Blocks of main text, marked, with clutter between them now and then."""
        r = self.r
        out = []
        text = lambda low, high: MARK + self.words(low, high)
        if r.random() < 0.8:
            h = f"<h1>{text(2, 12)}</h1>"
            out.append(f"<header>{h}</header>" if r.random() < 0.1 else h)
        loose = r.random() < 0.12
        for _ in range(r.choice([1, 1, 2, 3, 5, 8, 13])):
            kind, long_ = r.random(), r.choice([2, 8, 30, 80, 160])
            if loose:
                out.append(f"<div>{text(1, long_)}</div>" if kind < 0.8 else text(1, long_) + "<br>")
            elif kind < 0.7:
                inner = text(1, long_)
                if r.random() < 0.15:
                    inner += f' <a href="/z">{self.words(1, 4)}</a> ' + self.words(1, 10)
                if r.random() < 0.15:
                    inner = inner.replace(" ", " <b>", 1) + "</b>"
                if r.random() < 0.06:
                    inner += " " + r.choice(["<math><mi>x</mi><mo>=</mo><mn>2</mn></math>", "<svg><text>ab</text></svg>", "<canvas>c d</canvas>"]) + " " + self.words(1, 10)
                p = f"<p{self.hide() if r.random() < 0.05 else ''}>"
                out.append(r.choice([f"{p}{inner}</p>", f"{p}{inner}</p>", f"{p}{inner}", f"{p}<b>{inner}<br>"]))
            elif kind < 0.78:
                out.append(f"<h{r.randint(2, 4)}>{text(1, 8)}</h2>")
            elif kind < 0.86:
                out.append("<ul>" + "".join(f"<li>{text(1, 20)}</li>" for _ in range(r.randint(1, 5))) + "</ul>")
            elif kind < 0.9:
                out.append(f"<blockquote><p>{text(3, 40)}</p></blockquote>")
            elif kind < 0.93:
                out.append("<table>" + "".join(f"<tr><td>{text(1, 5)}</td><td>{text(1, 5)}</td></tr>" for _ in range(r.randint(1, 4))) + "</table>")
            elif kind < 0.96:
                out.append(f"<pre>{text(2, 20)}</pre>")
            else:
                out.append(f"<figure><img src=x><figcaption>{text(2, 12)}</figcaption></figure>")
            if r.random() < 0.08:
                out.append(self.clutter())
        if r.random() < 0.12:
            out.append(self.comments())
        return "".join(out)

    def page(self) -> str:
        r = self.r
        main = self.box("article article article main main div div section", "article content entry post story main text prose markdown article-body articleBody post-content entry-content", self.main(), bare=0.12)
        for _ in range(r.choice([0, 0, 0, 1, 2])):
            main = self.box("main div div section", "content main page container wrap layout", main + r.choice(["", "", self.comments(), self.clutter()]), bare=0.4)
        head, tail = [], []
        if r.random() < 0.5:
            head.append(self.box("header header div", "header head masthead top topbar banner navbar", r.choice([self.words(1, 4), f"<h1>{self.words(1, 4)}</h1>", f"<p>{self.words(1, 8)}</p>"]) + r.choice(["", self.links(2, 6), f"<nav>{self.links(2, 6)}</nav>"]), bare=0))
        if r.random() < 0.75:
            head.append(self.box("nav nav nav div ul", "nav menu navbar navigation main-menu", self.links(), bare=0))
        if r.random() < 0.2:
            head.append(self.box("div ol nav", "breadcrumb breadcrumbs", self.links(2, 4), bare=0))
        for _ in range(r.choice([0, 0, 1, 1, 2])):
            head.append(self.clutter())
        if r.random() < 0.4:
            (head if r.random() < 0.3 else tail).append(self.box("aside aside div", "sidebar side sideBar widget bar", "".join(r.choice([self.blurb, self.links, self.form])() for _ in range(r.randint(1, 3))), bare=0))
        if r.random() < 0.3:
            tail.append(self.comments())
        for _ in range(r.choice([0, 0, 1, 1])):
            tail.append(self.clutter())
        if r.random() < 0.8:
            tail.append(self.box("footer footer div", "footer foot copyright bottom", r.choice(["", self.links(2, 6)]) + r.choice([f"&copy; {self.words(1, 8)}", f"<p>{self.words(2, 20)}</p>", f"&copy; x &middot; {self.words(3, 12)}"]), bare=0))
        r.shuffle(head)
        body = "".join(head) + f"<!-- {self.words(1, 3)} -->" + main + "".join(tail)
        if r.random() < 0.3:
            body = f"<div{r.choice(['', self.attrs('page', 'wrap', 'container')])}>{body}</div>"
        return f"<!DOCTYPE html><html><head><title>{self.words(2, 8)}</title><style>p{{margin:0}}</style><script>var a='</p>';</script></head><body>{body}</body></html>"


def labelled(page: str) -> tuple[dom.Node, list[dom.Node]]:
    """An invented page's nodes with labels; a node is main text if a run below it is."""
    root, nodes = dom.parse(page)
    for x in reversed(nodes):
        if x.tag == "#run" and MARK in x.text:
            x.text, x.y = x.text.replace(MARK, ""), 1
        if x.y and x.parent:
            x.parent.y = 1
    return root, nodes


@lru_cache(maxsize=2)
def train(pages: int = TRAINING_PAGES, seed: int = SEED) -> Model:
    """Trees see each half of the pages with token odds of the other half, so that they learn what odds are worth on
    pages that the odds don't come from."""
    inventor = Inventor(seed)
    made = [labelled(inventor.page()) for _ in range(pages)]
    halves = made[::2], made[1::2]
    x = [features(*p, odds) for half, odds in zip(halves, [token_odds([n for _, n in other]) for other in halves[::-1]]) for p in half]
    y = [node.y for half in halves for _, nodes in half for node in nodes]
    return Model(Boosted().fit(np.concatenate(x), np.array(y, float)), token_odds([n for _, n in made]))


def main_text(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """(page_id, url, text, n_chars). No shuffle; the model (some 100 KB) goes with the tasks."""
    model = model or train()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        pages, texts = batch.column(2).to_pylist(), []
        for i in range(0, len(pages), CHUNK):
            texts += extract(pages[i : i + CHUNK], model)
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pick(pages, page_id="long", url="string", html="string").mapInArrow(batches(kernel), "page_id long, url string, text string, n_chars long")
