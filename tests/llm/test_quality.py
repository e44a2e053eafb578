"""Perplexity bands against a plain model of dictionaries, on rows that repeat, clash and have null ids, dealt in several ways."""

import math
from collections import Counter, defaultdict

import pytest

from slicelink.llm import quality

from .test_operators import plain_counts


def plain_model(texts, order=quality.ORDER):
    """P(byte | context) of one language's texts: modified Kneser-Ney by the book."""
    counts = {order: Counter()}
    for t in texts:
        b = b"\0" * (order - 1) + t.encode()
        counts[order].update(b[i : i + order] for i in range(len(b) - order + 1))
    for k in range(order - 1, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    rule, groups = {}, {}
    for k, c in counts.items():
        n = Counter(c.values())
        y = n[1] / (n[1] + 2 * n[2]) if n[1] else 0
        rule[k] = [min(max(j - (j + 1) * y * (n[j + 1] / n[j] if n[j] else 0), 0.05), j - 0.05) if n[1] and n[2] else 0.5 for j in (1, 2, 3)]
        groups[k] = defaultdict(lambda: [0, 0.0])
        for g, m in c.items():
            groups[k][g[:-1]][0] += m
            groups[k][g[:-1]][1] += rule[k][min(m, 3) - 1]

    def p(g):
        k = len(g)
        if not k:
            return 1 / 256
        c, low = counts[k][g], p(g[1:])
        s, d = groups[k].get(g[:-1], (0, 0.0))
        return low if not s else ((c - rule[k][min(c, 3) - 1] if c else 0) + d * low) / s

    return lambda t: sum(math.log(p((b"\0" * (order - 1) + t.encode())[i : i + order])) for i in range(len(t.encode())))


def plain_verdicts(rows):
    """(bits, base_failed, kept) of each (id, text, lang)."""
    by = defaultdict(list)
    for _, t, lang in rows:
        by[lang or ""].append(t or "")
    models, limits, bits = {x: plain_model(ts) for x, ts in by.items()}, {}, {}
    for lang, ts in by.items():
        for t in set(ts) - {""}:
            bits[lang, t] = round(-models[lang](t) / math.log(2) / len(t.encode()), 6)
        steps = sorted(math.floor(bits[lang, t] * quality.STEPS) for t in ts if t)
        q = [steps[math.ceil(f * len(steps)) - 1] / quality.STEPS for f in (0.25, 0.5, 0.75)] if steps else None
        limits[lang] = q and (q[1], max((q[1] - q[0]) * quality.BELOW, quality.LEAST_WIDTH), max((q[2] - q[1]) * quality.ABOVE, quality.LEAST_WIDTH))
    out = []
    for _, t, lang in rows:
        n, _, _, _, again = plain_counts(t)
        failed, b, fits = n < 20 or 100 * again > 30 * n, bits.get((lang or "", t or "")), True
        if b is not None:
            middle, below, above = limits[lang or ""]
            wide = math.sqrt(1 + quality.LENGTH / len(t.encode()))
            fits = middle - below * wide <= b <= middle + above * wide
        out.append((b, failed, not failed and fits))
    return out


@pytest.fixture(scope="module")
def rows(spark, sf):
    some = [(r.doc_id, r.text, r.lang) for r in spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 70").collect()]
    odd = [(None, some[3][1], some[3][2]), (None, some[4][1], None), (3, some[5][1], some[5][2]), some[6], some[6], (9, None, "en"), (None, "", None), (7, "$$ %% || " * 30, "en"), (8, "short one", "xx"), (8, "zq " * 8 + "wv " * 14, "xx")]
    return some + odd


@pytest.mark.parametrize("most, parts", [(quality.MOST_ENTRIES, 1), (quality.MOST_ENTRIES, 7), (0, 3)])
def test_verdicts_equal_plain_ones(spark, rows, most, parts):
    got = quality.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(parts), most=most).collect()
    want = plain_verdicts(rows)
    near = lambda b: b is None or round(b, 4)
    assert Counter((r.doc_id, r.lang, near(r.bits), r.base_failed, r.kept) for r in got) == Counter((i, lang or "", near(b), f, k) for (i, _, lang), (b, f, k) in zip(rows, want, strict=True))


def test_many_languages_join_by_merge(spark, rows, monkeypatch):
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    want = Counter((r.doc_id, r.bits, r.kept) for r in quality.judge(df).collect())
    monkeypatch.setattr(quality, "MOST_LANGUAGES", 0)
    assert Counter((r.doc_id, r.bits, r.kept) for r in quality.judge(df).collect()) == want


def test_the_bands_reject_what_labels_call_bad(spark):
    """Of documents that pass the base rules the bands take more of those labelled bad than of those labelled good."""
    where = "/root/testdata/sf0.01"
    got = quality.op10_quality(spark, where).where("NOT base_failed").join(spark.read.parquet(f"{where}/labels.parquet"), "doc_id").select("kept", "quality").collect()
    share = lambda q: sum(not r.kept for r in got if r.quality == q) / sum(r.quality == q for r in got)
    assert share(0) >= 0.1 and share(1) <= 0.02
