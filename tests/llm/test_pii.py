"""The skip-chain field: its edges, its independence of batches, and its added spans against exact inference."""

import itertools
import random
import re
import time

import numpy as np
import pyarrow as pa

from slicelink.llm import pii

from .test_operators import WORD, plain_base


def edges(text):
    g = pii.graph_of([text.split()])
    return list(zip(g.a, g.b, g.kind, strict=True))


def test_skip_edges_join_repetitions_that_are_no_neighbours():
    x = "555-123-4567"
    assert edges(f"call {x} or {x}") == [(0, 1, 1)]
    assert edges(f"call {x} {x}") == [(0, 1, 0)]
    assert edges(f"{x} and 12 then {x} x {x}") == [(0, 2, 1), (2, 3, 1)]


def test_equal_texts_equal_spans_in_any_batch():
    made = [" ".join(w) for w, _ in pii.labelled_texts(120, 5)]
    model = pii.default_model()
    whole = pii.find(pa.array(made), model)
    alone = [pii.find(pa.array([t]), model) for t in made]
    assert whole == ([b[0] for b, _ in alone], [e[0] for _, e in alone])
    back = pii.find(pa.array(made[::-1]), model)
    assert back == (whole[0][::-1], whole[1][::-1])


def exact(text, model):
    """Base spans and added spans of a text by enumeration of all labellings (marginal of each node, and how sure it is)."""
    weights, pair = model
    words = [(m.start(), m[0]) for m in re.finditer(WORD, text)]
    base = plain_base(text)
    nodes = [i for i, (_, w) in enumerate(words) if re.search("[0-9@]", w)]
    over = lambda i: {k for a, k, z in base if a < words[i][0] + len(words[i][1]) and z > words[i][0]}
    unary, links, latest = [], [], {}
    for n, i in enumerate(nodes):
        word = lambda j: words[j][1] if j >= 0 else ""
        on = pii.features(words[i][1], (word(i - 1), word(i - 2)), i - 1 in nodes, i + 1 in nodes, over(i))
        unary.append(weights[on].sum(0))
        if i - 1 in nodes:
            links.append((n - 1, n, 0))
        key = pii.link_key(words[i][1])
        if key is not None:
            if key in latest and (latest[key], n, 0) not in links:
                links.append((latest[key], n, 1))
            latest[key] = n
    share = np.zeros((len(nodes), len(pii.LABELS)))
    for s in itertools.product(range(len(pii.LABELS)), repeat=len(nodes)):
        share[range(len(nodes)), s] += np.exp(sum(u[x] for u, x in zip(unary, s, strict=True)) + sum(pair[t][s[a], s[b]] for a, b, t in links))
    share /= share.sum(1, keepdims=True)
    added, k = [], 0
    while k < len(nodes):
        z = k + 1
        while z < len(nodes) and nodes[z] == nodes[z - 1] + 1 and share[z].argmax() == share[k].argmax():
            z += 1
        label, group = int(share[k].argmax()), nodes[k:z]
        if label and share[k:z].max(1).min() >= pii.SURE and not any(over(i) for i in group):
            (s, w), (t, v) = words[group[0]], words[group[-1]]
            a, b = s + len(w) - len(w.lstrip(pii._EDGE)), t + len(v.rstrip(pii._EDGE))
            if a < b and pii._plausible(label - 1, text[a:b]) and not any(p < b and q > a for p, _, q in base):
                added.append((a, label - 1, b))
        k = z
    return base, sorted([*base, *added]), share


def test_added_spans_against_enumeration():
    r, seen, more = random.Random(9), 0, 0
    model = pii.default_model()
    for words, _ in pii.labelled_texts(400, 31):
        a = r.randrange(max(1, len(words) - 14))
        text = " ".join(words[a : a + 14])
        if sum(bool(re.search("[0-9@]", w)) for w in text.split()) > 5:
            continue
        base, every, share = exact(text, model)
        if len(share) and np.abs(share.max(1) - pii.SURE).min() < 0.05:
            continue  # loopy messages are not exact, so certainties near the limit may fall to either side
        got = pii.find(pa.array([text]), model)
        assert (got[0][0], got[1][0]) == (base, every)
        seen, more = seen + 1, more + len(every) - len(base)
    assert seen > 150 and more > 20


def test_spans_over_words_without_a_cap_and_in_linear_time():
    many = "a@b.co,c@d.co,e@f.co,g@h.co,i@j.co,k@l.co,m@n.co,o@p.co,q@r.co,1.2.3.4 " + "key abcdef0123456789abcdef "
    model, took = pii.default_model(), []
    for n in (200, 800):
        t = time.time()
        base, every = pii.find(pa.array([many * n]), model)
        took.append(time.time() - t)
        assert len(base[0]) == 10 * n and len(every[0]) == 11 * n
    assert took[1] < 12 * max(took[0], 0.2)


def test_rows_of_any_id(spark):
    rows = [(1, "a@b.co"), (1, "a@b.co"), (1, None), (None, "a@b.co"), (None, "")]
    got = sorted(((x.doc_id, x.n_email, x.spans) for x in pii.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    assert got == sorted([(1, 1, "email:0:6"), (1, 1, "email:0:6"), (1, 0, ""), (None, 1, "email:0:6"), (None, 0, "")], key=repr)
