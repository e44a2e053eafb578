"""Personal data: patterns, and a skip-chain conditional random field that adds what patterns alone don't see.

Nodes are the words of a text that hold a digit or an "@" (any other word can't be labelled and is left out of the
graph: names of people are not among the labels). Nodes of neighbouring words share chain potentials; nodes that repeat
an earlier one, or its last digits, share skip potentials with its latest occurrence, however near or far, unless the
two are neighbouring words. Loopy sum-product messages over all texts of a batch at once, as many rounds for each text,
give the marginals; weights maximise the likelihood on labelled texts by the same messages. Labels: none, the four
pattern kinds, and secret. Spans of the patterns always stay; the field's spans are added where they are certain
enough (SURE), plausible for their kind and clear of pattern spans.

Defined results: every row gives one row, whatever its id (null and repeated ones too); null text is an empty one;
texts without spans have counts of 0 and empty lists; equal texts, equal spans, in any batch; of labels with equal
marginals the first listed is taken; an empty table gives no rows; further columns are ignored. Offsets are code
points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa

from .common import Words, as_text, ready, slices, table

KINDS = ("email", "ip", "card", "phone", "secret")
LABELS = ("none", *KINDS)
SURE = 0.9
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# possessive and anchored at a run's start: the same matches in linear time
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2]))
    return (total + sum((0, 2, 4, 6, 8, 1, 3, 5, 7, 9)[int(d)] for d in digits[-2::-2])) % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the four patterns, each kind leftmost without overlap, in order."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > free and text[begin - 1] in _LOCAL:
            begin -= 1
        if begin < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((begin, 0, m.end()))
            free = m.end()
            at = text.find("@", free)
        else:
            at = text.find("@", at + 1)
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) < 4 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split(".")):
            out.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() < 40 and 12 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= len(_digits(m[0])) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


_EDGE = ".,;:!?\"'<>[]{}%#$&*=|"
_MAIL, _ADDRESS = re.compile(r"[\w.%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), re.compile(r"\d{1,3}(\.\d{1,3}){3}")
_AREA, _LOCAL_NO, _FULL_NO = re.compile(r"\(\d{2,4}\)"), re.compile(r"\d{3}[-.]\d{4}"), re.compile(r"\(?\d{2,4}\)?[-.]\d{3,4}[-.]\d{3,4}")
_HEX = re.compile(r"(?=.*\d)(?=.*[A-Za-z])[A-Za-z0-9_+/=-]{20,}")
_SECRET_CUES = frozenset("token key secret password passwd api_key apikey auth bearer".split())
_PHONE_CUES = frozenset("tel phone call fax mobile cell whatsapp".split())
FEATURES = ("bias", "at", "mail", "address", "plus", "area", "local", "full", "n1_3", "n4", "n5_8", "n9_11", "n12_19", "n20", "luhn", "mixed_long", "mixed", "secret_cue", "phone_cue", "after", "before", "figure", "in_email", "in_ip", "in_card", "in_phone")
F_AT = {f: i for i, f in enumerate(FEATURES)}


def features(word: str, back: tuple[str, str], after: bool, before: bool, inside: set[int]) -> list[int]:
    """The indices of a word's features. back: the two words before; after, before: whether the neighbours are nodes; inside: base kinds."""
    core = word.strip(_EDGE)
    d = _digits(core)
    on = [0]
    add = lambda f, yes: on.append(F_AT[f]) if yes else None
    add("at", "@" in core)
    add("mail", _MAIL.fullmatch(core))
    add("address", _ADDRESS.fullmatch(core))
    add("plus", core[:1] == "+" and core[1:2].isdigit())
    add("area", _AREA.fullmatch(core))
    add("local", _LOCAL_NO.fullmatch(core))
    add("full", _FULL_NO.fullmatch(core))
    if core.isdigit():
        n = len(core)
        add("n1_3" if n < 4 else "n4" if n == 4 else "n5_8" if n < 9 else "n9_11" if n < 12 else "n12_19" if n < 20 else "n20", True)
    add("luhn", 12 <= len(d) <= 19 and luhn(d))
    add("mixed_long", _HEX.fullmatch(core))
    add("mixed", not core.isdigit() and any(c.isalpha() for c in core) and "@" not in core)
    cues = {w.strip(_EDGE + "()").lower() for w in back}
    add("secret_cue", cues & _SECRET_CUES)
    add("phone_cue", cues & _PHONE_CUES)
    add("after", after)
    add("before", before)
    add("figure", re.fullmatch(r"\d+([.,:/-]\d+)+", core) and not _ADDRESS.fullmatch(core))
    for k in inside:
        if k < 4:
            on.append(F_AT["in_email"] + k)
    return on


def link_key(word: str) -> str | None:
    """Nodes with the same key are taken for repetitions of each other."""
    core = word.strip(_EDGE + "()")
    d = _digits(core)
    if "@" not in core and len(d) >= 7 and len(d) * 2 > len(core):
        return d[-7:]
    return core.lower() if len(core) >= 6 else None


class Graph:
    """Nodes of many texts: features, (doc, word) of each, and edges of type 0 (chain) or 1 (skip)."""

    def __init__(self):
        self.on: list[list[int]] = []
        self.where: list[tuple[int, int]] = []
        self.a: list[int] = []
        self.b: list[int] = []
        self.kind: list[int] = []

    def add(self, doc: int, words: list[tuple[int, str, tuple[str, str], set[int]]], skip: bool = True):
        """words: (index, word, the two before, base kinds over it) of the text's nodes, in order."""
        base, latest = len(self.on), {}
        for k, (i, w, back, inside) in enumerate(words):
            after, before = k > 0 and words[k - 1][0] == i - 1, k + 1 < len(words) and words[k + 1][0] == i + 1
            self.on.append(features(w, back, after, before, inside))
            self.where.append((doc, i))
            if after:
                self._edge(base + k - 1, base + k, 0)
            key = link_key(w) if skip else None
            if key is not None:
                if key in latest and not (after and latest[key] == base + k - 1):
                    self._edge(latest[key], base + k, 1)
                latest[key] = base + k

    def _edge(self, a, b, kind):
        self.a.append(a)
        self.b.append(b)
        self.kind.append(kind)

    def matrix(self) -> np.ndarray:
        x = np.zeros((len(self.on), len(FEATURES)))
        for i, on in enumerate(self.on):
            x[i, on] = 1
        return x

    def unary(self, weights: np.ndarray) -> np.ndarray:
        """matrix() @ weights, the same for a node in every batch: the features are added up in their order."""
        out = np.zeros((len(self.on), weights.shape[1]))
        row = np.repeat(np.arange(len(self.on)), [len(on) for on in self.on])
        np.add.at(out, row, weights[[i for on in self.on for i in on]])
        return out

    def edges(self):
        return np.array(self.a, np.int64), np.array(self.b, np.int64), np.array(self.kind, np.int64)


def _lse(x, axis):
    m = x.max(axis, keepdims=True)
    return np.squeeze(m, axis) + np.log(np.exp(x - m).sum(axis))


def beliefs(unary: np.ndarray, a: np.ndarray, b: np.ndarray, kind: np.ndarray, pair: np.ndarray, rounds: int = 30, hold: float = 0.3):
    """Marginals (n, L) and edge marginals (e, L, L: a, b) by loopy sum-product; pair: (2, L, L), symmetric.

    The number of rounds is fixed, so that no text's messages depend on the others of its batch.
    """
    n, labels = unary.shape
    e = len(a)
    src, dst = np.concatenate([a, b]), np.concatenate([b, a])
    turn = np.concatenate([np.arange(e, 2 * e), np.arange(e)])
    pot = pair[np.concatenate([kind, kind])]
    sent = np.zeros((2 * e, labels))
    total = unary.copy()
    for _ in range(rounds if e else 0):
        new = _lse(pot + (total[src] - sent[turn])[:, :, None], 1)
        new -= _lse(new, 1)[:, None]
        new = hold * sent + (1 - hold) * new
        sent = new
        total = unary.copy()
        for k in range(labels):
            total[:, k] += np.bincount(dst, sent[:, k], n)
    one = np.exp(total - _lse(total, 1)[:, None])
    joint = pot[:e] + (total[a] - sent[turn[:e]])[:, :, None] + (total[b] - sent[:e])[:, None, :]
    joint = np.exp(joint - joint.max((1, 2), keepdims=True)) if e else joint
    return one, joint / joint.sum((1, 2), keepdims=True) if e else joint


def fit(graph: Graph, labels: np.ndarray, rounds: int = 120, rate: float = 0.3, decay: float = 2e-4):
    """Unary weights (features, labels) and symmetric pair potentials (2, labels, labels)."""
    x, (a, b, kind), n = graph.matrix(), graph.edges(), len(LABELS)
    w, pair = np.zeros((x.shape[1], n)), np.zeros((2, n, n))
    y = np.eye(n)[labels]
    seen = np.zeros_like(pair)
    np.add.at(seen, (kind, labels[a], labels[b]), 1)
    sw, sp = np.full_like(w, 1e-6), np.full_like(pair, 1e-6)
    for _ in range(rounds):
        one, joint = beliefs(x @ w, a, b, kind, pair, rounds=8)
        gw = x.T @ (y - one) - decay * len(x) * w
        gp = seen - np.stack([joint[kind == t].sum(0) for t in (0, 1)]) - decay * len(x) * pair
        gp = gp + gp.transpose(0, 2, 1)
        sw, sp = sw + gw**2, sp + gp**2
        w, pair = w + rate * gw / np.sqrt(sw), pair + rate * gp / np.sqrt(sp)
    return w, pair


def labelled_texts(n: int, seed: int = 11) -> list[tuple[list[str], list[int]]]:
    """(words, labels) of made-up texts: personal data in many forms, numbers that are none, repetitions of both."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice("aeiou" if i % 2 else "bcdfglmnprst") for i in range(r.randint(2, 9)))
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))

    def card():
        d = r.choice("3456") + num(r.choice([14, 14, 13]))
        d += next(c for c in "0123456789" if luhn(d + c))
        return [d] if r.random() < 0.7 or len(d) != 16 else [d[i : i + 4] for i in range(0, 16, 4)]

    def phone(d):
        return r.choice([["+1", f"({d[:3]})", f"{d[3:6]}-{d[6:]}"], ["+1", f"({d[:3]})", f"{d[3:6]}-{d[6:]}"], [f"({d[:3]})", f"{d[3:6]}-{d[6:]}"], [f"{d[:3]}-{d[3:6]}-{d[6:]}"], [f"+1{d}"], [f"{d[3:6]}-{d[6:]}"]])

    out = []
    for _ in range(n):
        items: list[tuple[list[str], int]] = []
        for _ in range(r.randint(1, 5)):
            kind = r.randrange(1, 6)
            if kind == 1:
                x = [f"{word()}.{num(2)}@{word()}{r.randint(1, 9)}.example.{r.choice(['com', 'org', 'net'])}"]
            elif kind == 2:
                x = [".".join(str(r.randint(1, 254)) for _ in range(4))]
            elif kind == 3:
                x = card()
            elif kind == 4:
                d = num(3) + num(3) + num(4)
                x = phone(d)
                if x == [f"{d[3:6]}-{d[6:]}"]:
                    items.append((["+1", f"({d[:3]})", f"{d[3:6]}-{d[6:]}"], 4))
                for _ in range(r.randint(0, 2)):
                    items.append((phone(d), 4))
            else:
                x = [r.choice(["token", "key", "secret", "password"]), "=", f'"{"".join(r.choice("0123456789abcdef") for _ in range(r.choice([32, 40, 40])))}"']
                if r.random() < 0.3:
                    items.append((x[2:], 5))
            items.append((x, kind))
            if r.random() < 0.3:
                items.append((x, kind))
        for _ in range(r.randint(1, 8)):
            x = r.choice([lambda: [num(r.randint(1, 8))], lambda: [str(r.randint(1900, 2030))], lambda: [f"{num(3)}-{num(4)}"], lambda: [f"{r.randint(1, 99)}.{num(2)}"], lambda: [f"{num(2)}/{num(2)}/{num(4)}"], lambda: [word() + num(2)], lambda: [f"v{r.randint(1, 9)}.{r.randint(0, 9)}"], lambda: [f"({num(4)})"], lambda: [num(r.randint(20, 30))], lambda: ["".join(r.choice("0123456789abcdef") for _ in range(r.randint(6, 12)))], lambda: [num(4), num(4)], lambda: [f"@{word()}"], lambda: [f"{num(1)},{num(3)},{num(3)}"], lambda: [f"{num(2)}-{num(2)}-{num(2)}"]])()
            items += [(x, 0)] * r.choice([1, 1, 1, 2])
        r.shuffle(items)
        words, labels = [], []
        for x, kind in items:
            for _ in range(r.randint(1, 12)):
                words.append(word() + ("." if r.random() < 0.1 else ""))
                labels.append(0)
            if kind == 4 and r.random() < 0.2:
                words.append(r.choice(["tel", "phone", "call"]))
                labels.append(0)
            tail = r.choice(["", "", "", ".", ",", "###", "%%%", "!!"])
            for k, w in enumerate(x):
                words.append(w + (tail if k == len(x) - 1 else ""))
                labels.append(kind if any(c.isdigit() for c in w) or "@" in w else 0)
        out.append((words, labels))
    return out


def graph_of(texts: list[list[str]], skip: bool = True) -> Graph:
    """The graph of texts given as words."""
    graph = Graph()
    for doc, words in enumerate(texts):
        text, begin = " ".join(words), 0
        spans, nodes = base_spans(text), []
        for i, w in enumerate(words):
            if "@" in w or any("0" <= c <= "9" for c in w):
                nodes.append((i, w, (words[i - 1] if i else "", words[i - 2] if i > 1 else ""), {k for s, k, e in spans if s < begin + len(w) and e > begin}))
            begin += len(w) + 1
        graph.add(doc, nodes, skip)
    return graph


@lru_cache(maxsize=4)
def default_model(n: int = 300, seed: int = 11):
    """The model fitted on n made-up labelled texts (the bound of the sample)."""
    made = labelled_texts(n, seed)
    graph = graph_of([w for w, _ in made])
    return fit(graph, np.array([made[d][1][i] for d, i in graph.where]))


def _plausible(kind: int, text: str) -> bool:
    d = len(_digits(text))
    return {0: "@" in text, 1: _ADDRESS.fullmatch(text) is not None, 2: 12 <= d <= 19, 3: 7 <= d <= 15, 4: len(text) >= 16}[kind]


def find(text: pa.Array, model, sure: float = SURE, skip: bool = True) -> tuple[list[list], list[list]]:
    """Base spans and all spans, as (start, kind, end), of each text."""
    words = Words(text)
    data = words.data
    live = ((data >= 48) & (data <= 57)) | (data == 64)
    upto = np.concatenate([[0], np.cumsum(live)])
    active = np.flatnonzero(upto[words.end] > upto[words.start])
    base: list[list] = [[] for _ in range(len(text))]
    if not len(active):
        return base, base
    strings = as_text(text)
    whole = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    begin = whole[words.start] - whole[words.offsets[words.doc]]
    graph, nodes = Graph(), {}
    of = words.doc[active]
    cuts = [*np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])).tolist(), len(of)]
    bytes_of = lambda i: data[words.start[i] : words.end[i]].tobytes().decode()
    for x, y in zip(cuts, cuts[1:], strict=False):
        doc = int(of[x])
        spans = base[doc] = base_spans(strings[doc].as_py())
        first, rows = int(words.first[doc]), []
        ways = [[(a, z) for a, k, z in spans if k == j] for j in range(4)]  # a kind's spans are in order and apart
        at = [0] * 4
        for i in active[x:y].tolist():
            w, s = bytes_of(i), int(begin[i])
            inside = set()
            for j, way in enumerate(ways):
                while at[j] < len(way) and way[at[j]][1] <= s:
                    at[j] += 1
                if at[j] < len(way) and way[at[j]][0] < s + len(w):
                    inside.add(j)
            back = (bytes_of(i - 1) if i > first else "", bytes_of(i - 2) if i > first + 1 else "")
            rows.append((i - first, w, back, inside))
            nodes[doc, i - first] = (w, s, bool(inside))
        graph.add(doc, rows, skip)
    weights, pair = model
    one, _ = beliefs(graph.unary(weights), *graph.edges(), pair)
    every = [list(b) for b in base]
    best, share = one.argmax(1), one.max(1)
    k, here, text = 0, -1, ""
    while k < len(best):
        doc, i = graph.where[k]
        label, z = int(best[k]), k + 1
        while z < len(best) and graph.where[z] == (doc, i + z - k) and best[z] == label:
            z += 1
        if label and share[k:z].min() >= sure:
            own = [nodes[graph.where[m]] for m in range(k, z)]
            if not any(inside for _, _, inside in own):  # a pattern's span ends in words, so it would hold one of these
                if doc != here:
                    here, text = doc, strings[doc].as_py()
                (w, s, _), (v, t, _) = own[0], own[-1]
                a = s + len(w) - len(w.lstrip(_EDGE))
                b = t + len(v.rstrip(_EDGE))
                if a < b and _plausible(label - 1, text[a:b]):
                    every[doc].append((a, label - 1, b))
        k = z
    return base, [sorted(x) for x in every]


def joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{z}" for a, k, z in spans)


def redacted(text: str, spans) -> str:
    """The text with every span (overlapping ones as one, named by the first) replaced by its kind."""
    out, at = [], 0
    for a, k, z in spans:
        if a >= at:
            out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = max(at, z)
    return "".join(out) + text[at:]


FOUND = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"


def scan(docs, model=None, id_col: str = "doc_id", text_col: str = "text"):
    """One row per text (FOUND)."""
    model = model or default_model()

    def run(batches):
        for part in slices(batches, "t"):
            base, every = find(part.column(1), model)
            counts = [pa.array([sum(k == j for _, k, _ in b) for b in base], pa.int64()) for j in range(4)]
            yield pa.RecordBatch.from_arrays([part.column(0), *counts, pa.array([hashlib.sha256(joined(b).encode()).hexdigest() for b in base]), pa.array([joined(e) for e in every]), pa.array([len(e) - len(b) for b, e in zip(base, every, strict=True)], pa.int64())], names=[x.split()[0] for x in FOUND.split(", ")])

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, FOUND)


def redact(docs, text_col: str = "text", model=None):
    """docs with the spans of `text_col` replaced by their kinds; all columns stay (null text stays null)."""
    model = model or default_model()
    at = docs.columns.index(text_col)

    def run(batches):
        for part in slices(batches, text_col):
            column = as_text(part.column(at))
            _, every = find(column, model)
            hit = [i for i, e in enumerate(every) if e]
            if hit:
                texts = part.column(at).to_pylist()
                for i in hit:
                    texts[i] = redacted(texts[i], every[i])
                part = part.set_column(at, part.schema.names[at], pa.array(texts, pa.string()))
            yield part

    ready(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)


def op1_pii(spark, sf_dir):
    return scan(table(spark, sf_dir, "documents"))
