"""Main-text extraction: a tree-structured graphical model over the DOM.

Every element is a binary variable (content or not) with unary features (tag, words of class and id, size, link
density, depth) and a potential shared with its parent. Sum-product messages go from the leaves to the root and back;
an element's marginal decides over the text that lies directly in it. Parameters maximise the likelihood of labelled
pages, with the gradient from the same messages; labelled_pages() makes such pages in many layouts, and fit() takes
any others.

What lies in an element of NEVER (menus, forms, scripts and the like) is out whatever its marginal, at any depth, but
for an article or main element in it, with which the model decides again; a form that holds an article, a main or an
h1 element is taken for the wrapping of its page and left to the model.

Defined results: null or empty html gives an empty text; unclosed and stray tags are taken as browsers do, roughly; a
tag without an end is dropped with what follows it, but a quote that never closes is no quote; every row gives one row,
whatever its id and url (null and repeated ones too); equal pages give equal texts; an element whose marginal is just
one half is out; an empty table gives no rows; further columns are ignored. Reading a page takes time in proportion to
its length.
"""

from __future__ import annotations

import html
import random
import re
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa

from .common import as_text, ready, slices, table

OPEN = re.compile(r"<(?:(!--)|([!?]|/(?![a-zA-Z]))|(/?)([a-zA-Z][^\s/>]*))")
QUOTE_OR_END = re.compile(r"[>\"']")
ATTRIBUTE = re.compile(r"(?<![^\s\"'<>/=])([^\s\"'<>/=]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
# fixed values: the language's void, raw-text and block elements, and which start closes an open paragraph or item
HEAD = frozenset("base basefont bgsound link meta title style script noscript template".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe xmp noembed noframes svg math".split())
BLOCK = frozenset("address article aside blockquote body button center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead title tr ul".split())
CLOSES_P = BLOCK - frozenset("body html head button li dd dt td th tr tbody thead tfoot option optgroup legend summary title".split())
SAME = {"li": {"li"}, "dd": {"dd", "dt"}, "dt": {"dd", "dt"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "optgroup": {"option", "optgroup"}, "tbody": {"thead", "tbody", "tr", "td", "th"}, "tfoot": {"tbody", "thead", "tr", "td", "th"}}
FENCE = frozenset("table ul ol dl select body html article section div main aside nav header footer form".split())
NEVER = frozenset("script style textarea title noscript template iframe xmp noembed noframes svg math head select option button input form nav".split())
WORDS = {
    "ad": "ad ads advert advertisement adverts adbox sponsor sponsored promo promotion banner", "menu": "nav navbar navigation menu breadcrumb breadcrumbs toolbar tabs pagination pager",
    "edge": "header footer masthead topbar bottom colophon copyright", "side": "sidebar side aside related recommended widget rail teaser", "notice": "cookie cookies consent notice popup modal overlay newsletter subscribe alert gdpr",
    "talk": "comment comments reply replies respond discussion disqus", "share": "share social follow login signup search form", "main": "article content main post story entry body text prose",
}
WORD_OF = {w: k for k, ws in WORDS.items() for w in ws.split()}
TAGS = "html body div p article main section header footer nav aside h1 h2 h3 ul ol li a b i em strong span table tr td form figure figcaption blockquote pre code dl dd dt".split()
TAG_AT = {t: i for i, t in enumerate(TAGS)}
NUMERIC = ("bias", "log_chars", "link_density", "short", "depth", "stops", "other_tag")
FEATURES = [f"tag:{t}" for t in TAGS] + [f"word:{k}" for k in WORDS] + list(NUMERIC)
AT = {f: i for i, f in enumerate(FEATURES)}
GROUPS = ("block", "inline")


class Page:
    """Elements in document order: tag, parent, attrs' words; texts: (element, string) in order."""

    __slots__ = ("tag", "parent", "words", "texts", "marks")

    def __init__(self, source: str):
        self.tag, self.parent, self.words, self.texts, self.marks = ["#root"], [-1], [()], [], []
        stack, at, end = [0], 0, len(source)
        tags, open_ = self.tag, Counter({"#root": 1})

        def cut(k):
            for e in stack[k:]:
                open_[tags[e]] -= 1
            del stack[k:]

        last = {q: source.rfind(q) for q in ">\"'"}
        while at < end:
            m = OPEN.search(source, at)
            if not m:
                break
            if m.start() > at:
                self.texts.append((stack[-1], source[at : m.start()]))
            if m[1]:  # a comment
                close = source.find("-->", m.end())
                at = close + 3 if close >= 0 else end
                continue
            if m[2]:
                at = self._after(source, m.end(), last, False)
                continue
            at = self._after(source, m.end(), last, True)
            attrs = source[m.end() : at - 1]
            name = m[4].lower()
            if m[3]:
                if open_[name]:
                    k = len(stack) - 1
                    while tags[stack[k]] != name:
                        k -= 1
                    cut(k)
                self.texts.append((stack[-1], "\n" if name in BLOCK else ""))
                continue
            self._imply(stack, name, open_, cut)
            tags.append(name)
            self.parent.append(stack[-1])
            here = len(tags) - 1
            self.words.append(self._attrs(attrs))
            self.texts.append((here, "\n" if name in BLOCK else " " if name == "br" else ""))
            if name in VOID or attrs.rstrip().endswith("/") and name not in BLOCK:
                continue
            if name in RAW:
                close = re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I).search(source, at)
                self.texts.append((here, source[at : close.start() if close else end]))
                at = self._after(source, close.end(), last, False) if close else end
                continue
            stack.append(here)
            open_[name] += 1
        if at < end:
            self.texts.append((stack[-1], source[at:]))

    @staticmethod
    def _after(source: str, at: int, last: dict, quotes: bool) -> int:
        """Where a tag ends: behind the next > outside of quotes; a quote counts after = only, and if it closes."""
        while at <= last[">"]:
            m = QUOTE_OR_END.search(source, at)
            if m[0] == ">":
                return m.end()
            at, k = m.end(), m.start()
            while quotes and k and source[k - 1].isspace():
                k -= 1
            if quotes and k and source[k - 1] == "=" and last[m[0]] >= at:
                at = source.find(m[0], at) + 1
        return len(source)

    def _imply(self, stack, name, open_, cut):
        tags = self.tag
        if open_["head"] and name not in HEAD:
            k = len(stack) - 1
            while tags[stack[k]] != "head":
                k -= 1
            cut(k)
        if name in CLOSES_P and open_["p"]:
            for k in range(len(stack) - 1, 0, -1):
                if tags[stack[k]] == "p":
                    cut(k)
                    break
                if tags[stack[k]] in FENCE:
                    break
        if name in SAME and any(open_[x] for x in SAME[name]):
            for k in range(len(stack) - 1, 0, -1):
                if tags[stack[k]] in SAME[name]:
                    cut(k)
                elif tags[stack[k]] in FENCE:
                    break

    @staticmethod
    def _attrs(source: str):
        if not source or "=" not in source:
            return ()
        out = []
        for k, a, b, c in ATTRIBUTE.findall(source):
            if k.lower() in ("class", "id", "role"):
                out += [WORD_OF[w] for w in re.split(r"[^a-z]+", (a or b or c).lower()) if w in WORD_OF]
        return tuple(out)

    def features(self) -> np.ndarray:
        n = len(self.tag)
        x = np.zeros((n, len(FEATURES)), np.float64)
        own, link, depth, stops = np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n)
        for e, s in self.texts:
            own[e] += len(s)
            stops[e] += s.count(".") + s.count(",")
        parent = self.parent
        for e in range(1, n):
            depth[e] = depth[parent[e]] + 1
        for e in range(n - 1, 0, -1):
            if self.tag[e] == "a":
                link[e] = own[e]
            if self.tag[e] in RAW:
                own[e] = 0
            own[parent[e]] += own[e]
            link[parent[e]] += link[e]
            stops[parent[e]] += stops[e]
        for e in range(n):
            x[e, TAG_AT[self.tag[e]] if self.tag[e] in TAG_AT else AT["other_tag"]] = 1
            for w in self.words[e]:
                x[e, AT["word:" + w]] = 1
        x[:, AT["bias"]] = 1
        x[:, AT["log_chars"]] = np.log1p(own) / 5
        x[:, AT["link_density"]] = link / np.maximum(own, 1)
        x[:, AT["short"]] = own < 40
        x[:, AT["depth"]] = np.minimum(depth, 12) / 6
        x[:, AT["stops"]] = np.minimum(1, 20 * stops / np.maximum(own, 1))
        return x

    def never(self) -> list[bool]:
        """Whether each element is one of NEVER or lies in one; article and main begin anew, forms around a page are none."""
        wraps = set()
        for e in range(len(self.tag) - 1, 0, -1):
            if self.tag[e] in ("article", "main", "h1") or e in wraps:
                wraps.add(self.parent[e])
        out = [False] * len(self.tag)
        for e in range(1, len(self.tag)):
            if self.tag[e] not in ("article", "main"):
                out[e] = out[self.parent[e]] or self.tag[e] in NEVER and not (self.tag[e] == "form" and e in wraps)
        return out

    def kinds(self) -> list[int]:
        return [0 if t in BLOCK else 1 for t in self.tag]


def sum_product(parent: np.ndarray, kind: np.ndarray, unary: np.ndarray, pair: np.ndarray):
    """Over a forest (a root's parent is -1, parents come first): log-partition of all trees, marginals (n, 2) and edge
    marginals (n, 2, 2: parent, child). unary: (n, 2), pair: (kinds, 2, 2). All elements of one depth go together."""
    n = len(parent)
    depth = np.zeros(n, np.int64)
    for e in range(n):
        if parent[e] >= 0:
            depth[e] = depth[parent[e]] + 1
    levels = [np.flatnonzero(depth == d) for d in range(int(depth.max(initial=0)) + 1)]
    up, sent, edges = unary.copy(), np.zeros((n, 2)), np.zeros((n, 2, 2))
    for at in levels[:0:-1]:
        sent[at] = np.logaddexp.reduce(pair[kind[at]] + up[at][:, None, :], 2)
        np.add.at(up, parent[at], sent[at])
    root = levels[0]
    both, total = np.zeros((n, 2)), np.zeros(n)
    both[root] = up[root]
    total[root] = np.logaddexp(up[root, 0], up[root, 1])
    for at in levels[1:]:
        total[at] = total[parent[at]]
        joint = (both[parent[at]] - sent[at])[:, :, None] + pair[kind[at]] + up[at][:, None, :]
        edges[at] = np.exp(joint - total[at][:, None, None])
        both[at] = np.logaddexp(joint[:, 0], joint[:, 1])
    return total[root].sum(), np.exp(both - total[:, None]), edges


def marginals(page: Page, unary: np.ndarray, pair: np.ndarray) -> list[float]:
    """P(content) of each element: the messages in plain floats, as pages have few elements."""
    from math import exp, log1p

    n, parent, kind, pair = len(page.tag), page.parent, page.kinds(), pair.tolist()
    up = unary.tolist()
    sent = [None] * n
    for e in range(n - 1, 0, -1):
        a0, a1 = up[e]
        p, out = pair[kind[e]], []
        for q in p:
            x, y = q[0] + a0, q[1] + a1
            out.append(x + log1p(exp(y - x)) if x > y else y + log1p(exp(x - y)))
        sent[e] = out
        u = up[parent[e]]
        u[0] += out[0]
        u[1] += out[1]
    both, share = [None] * n, [0.0] * n
    both[0] = up[0]
    for e in range(n):
        if e:
            b, s, p, (a0, a1) = both[parent[e]], sent[e], pair[kind[e]], up[e]
            r0, r1 = b[0] - s[0], b[1] - s[1]
            now = []
            for c, a in ((0, a0), (1, a1)):
                x, y = r0 + p[0][c], r1 + p[1][c]
                now.append(a + (x + log1p(exp(y - x)) if x > y else y + log1p(exp(x - y))))
            both[e] = now
        d = both[e][0] - both[e][1]
        share[e] = 1 / (1 + exp(min(d, 700.0)))
    return share


def fit(pages: list[tuple[Page, np.ndarray]], rounds: int = 150, rate: float = 0.4, decay: float = 1e-3):
    """Weights (features,) and pair potentials (kinds, 2, 2) by gradient ascent on the labelled pages' likelihood."""
    w, pair = np.zeros(len(FEATURES)), np.zeros((len(GROUPS), 2, 2))
    first = np.cumsum([0] + [len(p.tag) for p, _ in pages])
    parent = np.concatenate([np.where((q := np.array(p.parent)) < 0, -1, q + at) for (p, _), at in zip(pages, first, strict=False)])
    kind = np.concatenate([p.kinds() for p, _ in pages])
    x, y = np.concatenate([p.features() for p, _ in pages]), np.concatenate([y for _, y in pages])
    child = np.flatnonzero(parent >= 0)
    seen = np.zeros_like(pair)
    np.add.at(seen, (kind[child], y[parent[child]], y[child]), 1)
    sw, sp = np.full_like(w, 1e-6), np.full_like(pair, 1e-6)
    for _ in range(rounds):
        score = x @ w
        _, one, edges = sum_product(parent, kind, np.stack([np.zeros_like(score), score], 1), pair)
        gw = x.T @ (y - one[:, 1]) - decay * w * len(pages)
        gp = seen - np.stack([edges[child][kind[child] == g].sum(0) for g in range(len(GROUPS))]) - decay * pair * len(pages)
        sw, sp = sw + gw**2, sp + gp**2
        w, pair = w + rate * gw / np.sqrt(sw), pair + rate * gp / np.sqrt(sp)
    return w, pair


def labelled_pages(n: int, seed: int = 7) -> list[tuple[str, list[str]]]:
    """(html, the article's blocks) in layouts drawn at random: where the article lies, which boilerplate stands around
    it and inside, how it is named, whether tags are closed."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice("aeiou" if i % 2 else "bcdfglmnprst") for i in range(r.randint(2, 9)))
    sentence = lambda k: " ".join(word() for _ in range(k)).capitalize() + r.choice(["." if r.random() < 0.9 else "", "!", "."])
    prose = lambda: " ".join(sentence(r.randint(3, 16)) for _ in range(r.randint(1, 8))) if r.random() < 0.85 else sentence(r.randint(1, 3))
    links = lambda: "<ul>" + "".join(f'<li><a href="/{word()}">{word()}</a></li>' for _ in range(r.randint(3, 9))) + "</ul>"
    out = []
    for _ in range(n):
        name = lambda kind: r.choice([f' class="{r.choice(WORDS[kind].split())}"', f' id="{r.choice(WORDS[kind].split())}"', f' class="{word()} {r.choice(WORDS[kind].split())}-{word()}"'])
        closed = r.random() < 0.7
        blocks, body = [], []

        def block(tag, text, shown=None, blocks=blocks, body=body, closed=closed):
            blocks.append(text)
            body.append(f"<{tag}>{shown or text}" + (f"</{tag}>" if closed or tag != "p" else ""))

        junk = {
            "nav": lambda: f"<nav{name('menu') if r.random() < 0.3 else ''}>{links()}</nav>", "menu": lambda: f"<div{name('menu')}>{links()}</div>", "ad": lambda: f"<div{name('ad')}>{prose()}</div>",
            "header": lambda: f"<header><div>{sentence(3)}</div>{links() if r.random() < 0.5 else ''}</header>", "edge": lambda: f"<div{name('edge')}>{sentence(5)}</div>",
            "aside": lambda: f"<aside><h3>{sentence(2)}</h3>{r.choice([links, lambda: f'<p>{prose()}</p>'])()}</aside>", "side": lambda: f"<div{name('side')}><p>{prose()}</p>{links()}</div>",
            "notice": lambda: f"<div{name('notice')}><p>{prose()}</p><button>{word()}</button></div>", "form": lambda: f"<form><label>{sentence(2)}</label><input name=q><textarea>{word()}</textarea></form>",
            "talk": lambda: f"<{(t := r.choice(['section', 'div', 'ol']))}{name('talk')}>" + "".join(f"<div><b>{word()}</b><p>{prose()}</p></div>" for _ in range(r.randint(1, 4))) + f"</{t}>",
            "footer": lambda: f"<footer>&copy; {word()} &middot; {prose()}</footer>", "share": lambda: f"<div{name('share')}>{links()}</div>", "script": lambda: f'<script>var a="<p>{word()}</p>";</script>',
        }
        block(r.choice(["h1", "h1", "h2"]), sentence(r.randint(2, 10)))
        for _ in range(r.randint(1, 12)):
            x = r.random()
            if x < 0.62:
                block("p", prose())
            elif x < 0.7:
                t = prose()
                block("p", t, f"<b>{t}" + ("</b>" if closed else "<br>"))
            elif x < 0.76:
                a, b = sentence(4), word()
                block("p", f"{a} {b} {a}", f'{a} <a href="/{b}">{b}</a> <em>{a}</em>')
            elif x < 0.82:
                block("h2", sentence(4))
            elif x < 0.88:
                items = [sentence(4) for _ in range(3)]
                blocks += items
                body.append("<ul>" + "".join(f"<li>{i}</li>" for i in items) + "</ul>")
            elif x < 0.92:
                block("blockquote", prose())
            else:
                body.append(junk[r.choice(["ad", "side", "share", "script", "notice", "aside"])]())
        inner = "".join(body)
        main = r.choice([lambda s: f"<article>{s}</article>"] * 3 + [lambda s: f"<main>{s}</main>", lambda s: f"<main><article>{s}</article></main>", lambda s: f"<div{name('main')}>{s}</div>", lambda s: f"<div><div{name('main')}>{s}</div></div>", lambda s: f"<section{name('main')}>{s}</section>"])
        before = [junk[k]() for k in r.sample(["nav", "menu", "ad", "header", "edge", "notice", "form", "share", "script", "aside"], r.randint(1, 5))]
        after = [junk[k]() for k in r.sample(["ad", "aside", "side", "talk", "footer", "edge", "form", "share", "nav"], r.randint(1, 5))]
        page = f"<!DOCTYPE html><html><head><title>{blocks[0]}</title><style>p{{margin:0}}</style></head><body>{''.join(before)}<!-- {word()} -->{main(inner)}{''.join(after)}</body></html>"
        out.append((page, blocks))
    return out


def label(page: Page, blocks: list[str]) -> np.ndarray:
    """1 for the elements whose text is one of the blocks' (each used in order), and for all that stands above them
    up to the lowest element that holds every block."""
    y = np.zeros(len(page.tag), np.int64)
    text: dict[int, str] = {}
    for e, s in page.texts:
        k = e
        while page.tag[k] not in BLOCK and k:
            k = page.parent[k]
        text[k] = text.get(k, "") + s
    todo = list(blocks)
    for e in sorted(text):
        t = " ".join(html.unescape(text[e]).split())
        if todo and t == todo[0] and page.tag[e] not in NEVER:
            y[e] = 1
            todo.pop(0)
    hits = np.flatnonzero(y)
    chains = []
    for e in hits:
        c, k = [], e
        while k > 0:
            c.append(k)
            k = page.parent[k]
        chains.append(c)
    if chains:
        common = set(chains[0]).intersection(*chains[1:])
        for c in chains:
            for k in c:
                if k not in common or k == max(common):
                    y[k] = 1
    for e in range(1, len(y)):  # inline elements go with the block they stand in
        if page.tag[e] not in BLOCK and page.tag[e] not in NEVER:
            y[e] = y[page.parent[e]]
    return y


@lru_cache(maxsize=4)
def default_model(n: int = 400, seed: int = 7):
    """The model fitted on n labelled pages (the bound of the sample)."""
    return fit([(p, label(p, blocks)) for source, blocks in labelled_pages(n, seed) for p in [Page(source)]])


def extract(source: str, model) -> str:
    page = Page(source)
    w, pair = model
    never = page.never()
    score = (page.features() * w).sum(1)  # the same for an element in every page, unlike a product of matrices
    unary = np.stack([np.zeros_like(score), score], 1)
    keep = [p > 0.5 for p in marginals(page, unary, pair)]
    for e in range(len(keep)):
        if never[e]:
            keep[e] = False
        elif page.tag[e] not in BLOCK and e:
            keep[e] = keep[page.parent[e]]  # text inside a block isn't torn
    blocks, now = [], []
    for e, s in page.texts:
        if s == "\n":
            blocks.append("".join(now))
            now = []
        elif s and keep[e]:
            now.append(s)
    blocks.append("".join(now))
    return "\n".join(t for b in blocks if (t := " ".join(html.unescape(b).split())))


def main_text(pages, model=None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html"):
    """page_id, url, text, n_chars of every page."""
    model = model or default_model()

    def run(batches):
        for part in slices(batches, "h"):
            text = [extract(h, model) for h in as_text(part.column(2)).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    ready(pages.sparkSession)
    return pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].alias("url"), pages[html_col].alias("h")).mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op9_htmltext(spark, sf_dir):
    return main_text(table(spark, sf_dir, "pages"))
