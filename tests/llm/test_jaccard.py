"""The chosen-path join against all pairs: chains, dense groups, deep splits, ids that repeat, and recall."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from slicelink.llm import jaccard

from .test_operators import plain_similar, prose


def changed(words, at, tag):
    return " ".join(w if i not in at else f"{tag}{i}" for i, w in enumerate(words))


@pytest.fixture(scope="module")
def mixed():
    """A chain in which only neighbours are similar, a dense group, loose texts that share a long passage, and pairs near the limit."""
    r = random.Random(3)
    rows, words = [], prose(120, 1, None).split()
    for i in range(40):  # each step changes four words more
        rows.append((i, " ".join(words)))
        for k in r.sample(range(120), 1):
            words[k] = f"c{i}x{k}"
    base = prose(150, 2, None).split()
    rows += [(100 + i, changed(base, {i}, f"d{i}n")) for i in range(40)]
    common = prose(60, 3, None)
    rows += [(200 + i, common + " " + prose(60, 100 + i, None)) for i in range(40)]
    for i in range(60):
        w = prose(100, 500 + i, None).split()
        rows += [(300 + 2 * i, " ".join(w)), (301 + 2 * i, changed(w, set(r.sample(range(100), 2)), "z"))]
    r.shuffle(rows)
    return rows


@pytest.mark.parametrize("block, wide", [(3, 5), (8, 8), (96, 512)])
def test_all_ways_find_the_links_of_all_pairs(spark, mixed, block, wide):
    got = {x.doc_id: (x.class_id, x.n_links) for x in jaccard.similar(spark.createDataFrame(mixed, "doc_id long, text string"), recall=0.999999, block=block, wide=wide).collect()}
    assert got == plain_similar(dict(mixed))


def test_small_buckets_and_dense_groups(spark, mixed):
    df = spark.createDataFrame(mixed, "doc_id long, text string")
    first = jaccard.written(jaccard.sketches(df), "sketches").selectExpr("u AS v", "sig", "doc_id")
    vs, dense = jaccard.buckets(first, 3, 3)
    assert all(1 < len(x.vs) <= 3 and x.vs == sorted(x.vs) for x in vs.collect())
    doc = {x.v: x.doc_id for x in first.collect()}
    assert {doc[x.v] for x in dense.collect()} >= set(range(100, 140))  # the near copies; loose texts are split
    assert {x.kind for x in jaccard.units(first, vs, dense, 3).collect()} >= {0, 2}


def test_nodes_of_alike_sets_are_not_split_again(spark, monkeypatch):
    """Whichever set is a node's first; sets that share a passage only are split."""
    base, r, write, judged = prose(100, 31, None).split(), random.Random(7), jaccard.written, []
    near = [changed(base, set(r.sample(range(100), 2)), f"g{i}n") for i in range(150)]
    loose = [" ".join(base[:50]) + " " + prose(50, 700 + i, None) for i in range(150)]

    def watched(df, name, **how):
        out = write(df, name, **how)
        if name == "large":
            judged.append(Counter(x.alike for x in out.select("p", "alike").distinct().collect()))
        return out

    monkeypatch.setattr(jaccard, "written", watched)
    for texts, alike in ((near, True), (loose, False)):
        judged.clear()
        first = jaccard.sketches(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).selectExpr("doc_id AS v", "sig").cache()
        dense = jaccard.buckets(first, 3, 20)[1]
        assert judged[0][alike] and not judged[0][not alike]
        assert not alike or {x.v for x in dense.collect()} == set(range(150))


def test_agreement_of_a_node_is_summed_over_its_parts(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "JUDGED", 3)
    texts = [changed(prose(100, 31, None).split(), {i}, f"g{i}n") for i in range(30)] + [prose(80, 700 + i, None) for i in range(30)]
    first = jaccard.sketches(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).selectExpr("doc_id AS v", "sig").cache()
    large = spark.createDataFrame([(v // 30, v, 30) for v in range(60)], "p long, v long, n long")
    assert {x.p: x.alike for x in jaccard.alike_nodes(large, first).collect()} == {0: True, 1: False}


def test_long_chains_are_compared_bucket_by_bucket(spark):
    words, texts = prose(120, 21, None).split(), []
    for i in range(60):
        texts.append(" ".join(words))
        words[(i * 37) % 120] = f"c{i}"
    sig = bytes(4 * jaccard.COORDINATES)
    first = spark.createDataFrame([(i, sig) for i in range(60)], "v long, sig binary")
    vs = spark.createDataFrame([([i, i + 1, i + 2],) for i in range(58)], "vs array<long>")
    units = jaccard.units(first, vs, spark.createDataFrame([(50, 50), (50, 51), (50, 52)], "m long, v long"), 4).collect()
    chain = [x for x in units if x.kind == 1]
    assert len(chain) == 3 * 57 and all(x.c in x.us for x in chain) and {x.v for x in units if x.kind == 2} == {50, 51, 52}  # 50 to 52 are compared as a group
    rows = sorted((x.kind, x.c, b, max(b, o), x.b, x.v, texts[x.v], x.us, x.d) for x in units for o in range(x.nb) for b in [min(x.b, o)])
    batch = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), [pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.int64()], strict=True)], names=["kind", "c", "x", "y", "b", "v", "t", "us", "d"])
    found = Counter()
    for out in jaccard._blocks([batch], 0.8):
        for v, n in zip(out.column(0).to_pylist(), out.column(1).to_pylist(), strict=True):
            found[v] += n
    sets = [frozenset(zip(*(t.split()[k:] for k in range(5)), strict=False)) for t in texts]
    linked = lambda x, y: len(sets[x] & sets[y]) >= 0.8 * len(sets[x] | sets[y])
    assert found == Counter({x: n for x in range(60) if (n := sum(linked(x, y) for y in range(60) if 0 < abs(x - y) <= 2))})


def test_ids_that_repeat_clash_or_are_null(spark):
    a, b, c = (prose(160, k, None) for k in (11, 12, 13))
    near = lambda t, k: changed(t.split(), {k}, "q")
    rows = [(1, a), (1, a), (1, b), (2, near(a, 5)), (3, near(b, 9)), (None, c), (None, near(c, 4)), (7, near(c, 60)), (None, "x"), (9, None), (9, "")]
    got = sorted(((x.doc_id, x.class_id, x.n_links, x.n_copies) for x in jaccard.similar(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    want = [(1, 1, 1, 2), (1, 1, 1, 2), (1, 1, 1, 1), (2, 1, 1, 1), (3, 1, 1, 1), (None, 7, 2, 1), (None, 7, 2, 1), (7, 7, 2, 1), (None, None, 0, 1), (9, 9, 0, 2), (9, 9, 0, 2)]
    assert got == sorted(want, key=repr)


def test_recall_over_pairs_near_the_limit():
    """In numpy: of pairs of a similarity of 0.8 to 0.85 the runs bring nearly all into a common node."""
    r, n = np.random.default_rng(5), 4000
    gram = r.integers(0, 2**63, (n, 100), dtype=np.uint64)
    other = gram.copy()
    k = 9  # 91 common of 109 in all
    other[:, :k] = r.integers(0, 2**63, (n, k), dtype=np.uint64)
    sig = [(jaccard.signatures(np.sort(x, 1).ravel(), np.arange(n) * 100) >> np.uint64(32)).astype(np.uint32).astype(np.uint64) for x in (gram, other)]
    runs = jaccard.runs_for()
    one, two = (jaccard.paths(s, jaccard.roots(n, runs)) for s in sig)
    met = np.array([len(np.intersect1d(x, y)) > 0 for x, y in zip(one, two, strict=True)])
    assert met.mean() >= 0.99
