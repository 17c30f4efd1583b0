"""Main text of web pages from a tree-structured graphical model over their blocks.

Every block element is a node with two states, content or not. Its own features (tag, class
words, amount of text and links) give evidence, and the tag of its parent decides how the
parent's state bears on its own. Messages pass up the tree and down again (sum-product), all
pages of a batch together, and the marginals decide. Potentials are learned from labelled pages.
"""

from __future__ import annotations

import html
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .shared import arrow_map, small_batches, to_batch

# Elements that form blocks, that have no end tag, whose content is no markup.
BLOCKS = set(
    "html head body address article aside blockquote button canvas caption center dd details dialog div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 header hgroup iframe label legend li main menu nav noscript object ol option p pre search section select summary svg table"
    " tbody td template tfoot th thead tr ul video audio".split()
)
RAW = {"script", "style", "title", "textarea", "xmp", "noembed", "noframes"}
VOID = {"hr", "br", "img", "input", "meta", "link", "area", "base", "col", "embed", "source", "track", "wbr"}
ENDS_PARAGRAPH = BLOCKS - {"html", "head", "body", "button", "canvas", "iframe", "label", "noscript", "object", "option", "select", "svg", "template", "video", "audio", "caption", "td", "th", "tr", "tbody", "thead", "tfoot", "legend"} | {"hr"}
SAME_LEVEL = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}}
STOPS = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}, "p": {"td", "th", "button", "caption", "object"}}
_token = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|</?[a-zA-Z][^>]*\Z""", re.S)
_attribute = re.compile(r"""(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_word = re.compile(r"[a-z]+")


class Page:
    """Nodes of one page: parents, depths, feature words and the text runs of each, in page order."""

    def __init__(self, text: str):
        self.tags, self.parents, self.depths, self.words = ["#root"], [-1], [0], [[]]
        self.size, self.linked, self.runs = [0], [0], []
        stack, run, links, at = [0], [], 0, 0

        def flush():
            nonlocal run
            if block := " ".join("".join(run).split()):
                self.size[stack[-1]] += len(block)
                self.runs.append((stack[-1], block))
            run = []

        def put(piece: str):
            if piece:
                piece = html.unescape(piece)
                run.append(piece)
                if links:
                    self.linked[stack[-1]] += len(piece.strip())

        while m := _token.search(text, at):
            put(text[at : m.start()])
            at = m.end()
            name = (m[2] or m[5] or "").lower()
            if not name:
                continue
            closing = m[1] or m[4]
            if name == "a":
                links = 0 if closing else 1
            elif name == "br":
                run.append(" ")
            elif name in RAW and not closing:
                end = re.compile(f"</{re.escape(name)}(?=[\\s/>]|$)[^>]*>?", re.I).search(text, at)
                at = end.end() if end else len(text)
            elif name in BLOCKS or name == "hr":
                flush()
                if closing:
                    for k in range(len(stack) - 1, 0, -1):
                        if self.tags[stack[k]] == name:
                            del stack[k:]
                            break
                    continue
                for shut, when in ((SAME_LEVEL.get(name, ()), True), ({"p"}, name in ENDS_PARAGRAPH)):
                    if shut and when:
                        stop = STOPS.get("p" if shut == {"p"} else name, ())
                        for k in range(len(stack) - 1, 0, -1):
                            if self.tags[stack[k]] in shut:
                                del stack[k:]
                                break
                            if self.tags[stack[k]] in stop:
                                break
                if name == "hr":
                    continue
                self.tags.append(name)
                self.parents.append(stack[-1])
                self.depths.append(len(stack))
                self.words.append(sorted({w for a in _attribute.finditer(m[3] or m[6] or "") for w in _word.findall((a[2] or a[3] or a[4] or "").lower())}))
                self.size.append(0)
                self.linked.append(0)
                if not (m[3] or m[6] or "").rstrip().endswith("/") or name not in VOID:
                    stack.append(len(self.tags) - 1)
        put(text[at:])
        flush()

    def features(self) -> list[list[str]]:
        children = np.bincount(np.array(self.parents[1:], np.int64), minlength=len(self.tags)) if len(self.tags) > 1 else [0]
        out = []
        for i, tag in enumerate(self.tags):
            size, linked = self.size[i], self.linked[i]
            share = linked / size if size else 0
            out.append([f"tag {tag}", *(f"word {w}" for w in self.words[i]), f"size {0 if not size else 1 if size < 25 else 2 if size < 100 else 3}", f"links {0 if share < 0.05 else 1 if share < 0.5 else 2}", f"leaf {int(not children[i])}"])
        return out


class ContentModel:
    """Evidence weights by feature, and state transitions by the parent's tag."""

    def __init__(self, weights: dict[str, float], bias: float, prior: float, moves: dict[str, tuple[float, float]], usual: tuple[float, float]):
        self.weights, self.bias, self.prior, self.moves, self.usual = weights, bias, prior, moves, usual

    @staticmethod
    def train(pages: list[tuple[Page, list[int]]], rounds: int = 300, ridge: float = 1e-3) -> ContentModel:
        """Logistic evidence from all labelled nodes; transitions from smoothed counts of parent and child states."""
        rows = [(f, y) for page, labels in pages for f, y in zip(page.features(), labels)]
        names = sorted({x for f, _ in rows for x in f})
        number = {x: i for i, x in enumerate(names)}
        x, y = np.zeros((len(rows), len(names))), np.array([r[1] for r in rows], float)
        for i, (f, _) in enumerate(rows):
            x[i, [number[k] for k in f]] = 1
        w, b, speed = np.zeros(len(names)), 0.0, np.zeros(len(names))
        for _ in range(rounds):
            gap = 1 / (1 + np.exp(-(x @ w + b))) - y
            g = x.T @ gap / len(rows) + ridge * w
            speed += g * g
            w -= 0.5 * g / np.sqrt(speed + 1e-9)
            b -= 0.5 * gap.mean()
        counts: dict[str, np.ndarray] = {}
        for page, labels in pages:
            for i, p in enumerate(page.parents):
                if p >= 0:
                    for key in (page.tags[p], ""):
                        counts.setdefault(key, np.full((2, 2), 0.0))[labels[p], labels[i]] += 1
        rate = lambda c, base: tuple((c[s, 1] + 2 * base[s]) / (c[s].sum() + 2) for s in (0, 1))
        usual = rate(counts.pop(""), (0.02, 0.98))
        mean = float(np.log(y.mean() / (1 - y.mean())))
        return ContentModel(dict(zip(names, w.tolist())), float(b), mean, {k: rate(c, (min(usual[0], 0.02), 0.98)) for k, c in counts.items()}, usual)

    def marginals(self, pages: list[Page]) -> list[np.ndarray]:
        """Probability of content of every node, for all pages at once, level by level."""
        sizes = [len(p.tags) for p in pages]
        first = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
        parent = np.concatenate([np.array(p.parents, np.int64) + f for p, f in zip(pages, first)])
        depth = np.concatenate([np.array(p.depths, np.int64) for p in pages])
        known = self.weights.get
        evidence = np.array([sum(known(x, 0.0) for x in f) for p in pages for f in p.features()]) + self.bias - self.prior
        tags = [t for p in pages for t in p.tags]
        move = np.array([self.moves.get(tags[q] if d else "", self.usual) for q, d in zip(parent, depth)])
        levels = [np.flatnonzero(depth == d) for d in range(depth.max() + 1)]
        up, message = evidence.copy(), np.zeros(len(depth))
        for at in reversed(levels[1:]):
            e = np.exp(np.clip(up[at], -60, 60))
            message[at] = np.log((move[at, 1] * e + 1 - move[at, 1]) / (move[at, 0] * e + 1 - move[at, 0]))
            np.add.at(up, parent[at], message[at])
        belief = np.zeros(len(depth))
        belief[levels[0]] = 1 / (1 + np.exp(-np.clip(up[levels[0]] - 6, -60, 60)))
        for at in levels[1:]:
            rest = np.clip(np.log(np.maximum(belief[parent[at]], 1e-30) / np.maximum(1 - belief[parent[at]], 1e-30)) - message[at], -60, 60)
            above = 1 / (1 + np.exp(-rest))
            down = above * move[at, 1] + (1 - above) * move[at, 0]
            odds = np.clip(np.log(down / (1 - down)) + up[at], -60, 60)
            belief[at] = 1 / (1 + np.exp(-odds))
        return [belief[a:b] for a, b in zip(first[:-1], first[1:])]


def labelled_pages(count: int = 240, seed: int = 5) -> list[tuple[Page, list[int]]]:
    """Training pages of several invented layouts; what stands between the comments ``main`` and ``out`` is content, but for parts between ``junk`` and ``end``."""
    r = random.Random(seed)
    text = lambda a, b: " ".join("".join(r.choice("abcdefghilmnoprstu") for _ in range(r.randint(1, 9))) for _ in range(r.randint(a, b)))
    link = lambda: f'<a href="/{r.random()}">{text(1, 3)}</a>'
    menu = lambda: "<ul>" + "".join(f"<li>{link()}</li>" for _ in range(r.randint(2, 9))) + "</ul>"
    pick = lambda *words: r.choice(words)

    def para() -> str:
        kind = r.random()
        body = text(1, 4) if kind < 0.25 else text(5, 120)
        if r.random() < 0.2:
            body = f"<b>{body}<br>"
        return f"<p>{body}" + ("</p>" if r.random() < 0.85 else "")

    def junk() -> str:
        return r.choice(
            [
                lambda: f"<nav>{menu()}</nav>",
                lambda: f'<div class="{pick("menu", "nav", "navbar", "breadcrumb", "sidebar", "related", "share", "social", "widget")}">{menu()}</div>',
                lambda: f'<div class="{pick("ad", "ads", "advert", "banner", "sponsor", "promo", "cookie", "notice", "popup", "newsletter")}">{pick("", "<p>")}{text(3, 40)}</div>',
                lambda: f"<aside>{para()}{pick('', menu())}</aside>",
                lambda: f"<form>{pick('', '<label>')}{text(1, 3)}<input><button>{text(1, 2)}</button></form>",
                lambda: f"<header>{pick('<h1>', '<h2>', '<div>')}{text(1, 6)}{pick('', menu())}</header>",
                lambda: f"<footer>{pick('', '<p>', '<div>')}&copy; {text(2, 25)}</footer>",
                lambda: f'<{pick("div", "section")} {pick("class", "id")}="{pick("comments", "comment", "replies", "discussion")}"><h3>{text(1, 3)}</h3>' + "".join(f'<div class="comment">{para()}</div>' for _ in range(r.randint(1, 4))) + "</div></section>",
            ]
        )()

    made = []
    for _ in range(count):
        parts = [f"<{pick('h1', 'h2')}>{text(2, 12)}</h1></h2>"]
        for _ in range(r.randint(1, 12)):
            parts.append(r.choices([para(), f"<h2>{text(1, 8)}</h2>", f"<ul><li>{text(3, 20)}</li><li>{text(3, 20)}</li></ul>", f"<blockquote>{para()}</blockquote>", f"<table><tr><td>{text(1, 5)}</td><td>{text(1, 9)}</td></tr></table>", f"<pre>{text(4, 20)}</pre>", f"<!--junk-->{junk()}<!--end-->"], [12, 1, 1, 1, 0.5, 0.3, 0.6])[0])
        holder = r.choices(["<article>{}</article>", "<main><article>{}</article></main>", '<div class="{c}">{}</div>', "<main>{}</main>", '<section class="{c}">{}</section>'], [8, 3, 3, 2, 1])[0]
        body = holder.replace("{c}", pick("content", "article", "post", "entry", "story", "text")).replace("{}", "<!--main-->" + "".join(parts) + "<!--out-->", 1)
        page = "".join(junk() for _ in range(r.randint(0, 4))) + body + "".join(junk() for _ in range(r.randint(0, 3)))
        if r.random() < 0.85:
            page = f"<html><head><title>x</title></head><body>{page}</body></html>"
        if r.random() < 0.1:
            page = page[: r.randint(len(page) // 2, len(page))]
        made.append(_labelled(page))
    return made


def _labelled(source: str) -> tuple[Page, list[int]]:
    """Turns the marking comments into labels: elements that open between main and out, outside junk, and the element that holds main."""
    inside = junk = False
    labels, order = [], []
    for m in re.finditer(r"<!--(main|out|junk|end)-->|<([a-z]+[0-9]?)", source):
        if m[1]:
            inside, junk = {"main": (True, False), "out": (False, False), "junk": (inside, True), "end": (inside, False)}[m[1]]
            if m[1] == "main" and order:
                labels[-1] = 1
        elif m[2] in BLOCKS:
            order.append(m[2])
            labels.append(int(inside and not junk))
    page = Page(source)
    if page.tags[1:] != order[: len(page.tags) - 1]:
        raise AssertionError("labels do not follow the nodes")
    return page, [0, *labels[: len(page.tags) - 1]]


_trained: list[ContentModel] = []


def trained_model() -> ContentModel:
    if not _trained:
        _trained.append(ContentModel.train(labelled_pages()))
    return _trained[0]


def main_text(pages: list[Page], model: ContentModel) -> list[str]:
    return ["\n\n".join(block for node, block in p.runs if m[node] > 0.5) for p, m in zip(pages, model.marginals(pages))] if pages else []


def extract(pages: DataFrame, model: ContentModel | None = None) -> DataFrame:
    """page_id, url, text, n_chars of every page; null or empty html gives an empty text.

    Pages of any length are read whole. An empty table gives no rows, repeated ids come out as
    often; other columns of the input play no part.
    """
    model = model or trained_model()

    def run(batches):
        for batch in small_batches(batches, rows=256):
            texts = main_text([Page(h or "") for h in batch.column(2).to_pylist()], model)
            yield to_batch({"page_id": batch.column(0), "url": batch.column(1), "text": pa.array(texts, pa.string()), "n_chars": pa.array([len(t) for t in texts], pa.int64())})

    return arrow_map(pages.select("page_id", "url", "html"), run, "page_id long, url string, text string, n_chars long")
