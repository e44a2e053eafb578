"""The dealt operators against brute force, round trips, planted cases and odd inputs."""

import base64
import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from slicelink.llm import htmltext, jaccard, licenses, matroska, packing, passages, pieces, pii, quality, registry, warc
from slicelink.llm.common import Words, written
from slicelink.llm.components import components

WORD = r"[^\x20\x09-\x0D]+"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [None, "", " ", "\n\n", "a", "one two three", "é" * 50, "x" * 5000, "word " * 3000, "a\x00b \U0001f600 ß 漢字 İ", "same text here for all", "same text here for all"]


def prose(n, seed, vocab=400):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8))) for _ in range(n)) if vocab is None else " ".join(f"w{r.randrange(vocab)}" for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Odd rows, with further columns whose names the operators use themselves."""
    rows = [(i, t, None if i % 3 == 0 else "en", "s", 0) for i, t in enumerate(ODD)]
    df = spark.createDataFrame(rows, DOCS)
    for c in ("t", "i", "h", "doc", "p", "v", "c", "b", "u", "r", "d", "digest", "dir", "name", "license", "class_id", "units"):
        df = df.withColumn(c, df.doc_id)
    return df


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.collect()}


ON_DOCS = {"pii": pii.scan, "pieces": pieces.encode, "packing": packing.pack, "passages": passages.passages, "jaccard": jaccard.similar, "matroska": matroska.digest, "quality": quality.judge, "licenses": lambda d: licenses.scan(licenses.placed(d))}


@pytest.mark.parametrize("name", sorted(ON_DOCS))
def test_odd_and_empty_inputs(odd, name):
    got = ON_DOCS[name](odd)
    if name not in ("packing", "passages"):
        assert sorted(r.doc_id for r in got.select("doc_id").collect()) == list(range(len(ODD)))
    assert ON_DOCS[name](odd.limit(0)).count() == 0


def test_registry_names():
    assert [n for n in range(1, 11) if not any(k.startswith(f"op{n}_") for k in registry.queries())] == []


# --- words


def test_words_and_grams():
    r = random.Random(1)
    made = ["".join(r.choice("ab \t\n\x0b\x0c\ré") for _ in range(r.randint(0, 40))) for _ in range(300)]
    w = Words(pa.array(made))
    for i, t in enumerate(made):
        a, z = w.first[i], w.first[i + 1]
        assert [w.data[x:y].tobytes().decode() for x, y in zip(w.start[a:z], w.end[a:z], strict=True)] == re.findall(WORD, t)
    seen: dict = {}
    for i in range(len(w.hash)):
        assert seen.setdefault(w.hash[i], w.data[w.start[i] : w.end[i]].tobytes()) == w.data[w.start[i] : w.end[i]].tobytes()


# --- 1


def plain_base(t):
    out = []
    for k, p in enumerate([r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"]):
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            if k == 1 and max(map(int, m[0].split("."))) > 255 or k == 2 and not (12 <= len(d) <= 19 and pii.luhn(d)) or k == 3 and not 9 <= len(d) <= 15:
                continue
            out.append((m.start(), k, m.end()))
    return sorted(out)


def test_pii_base_equals_patterns(texts):
    r = random.Random(2)
    made = ["".join(r.choice("0123456789..-+ @ab()%") for _ in range(r.randint(1, 90))) for _ in range(2000)]
    for t in [*made, *(x or "" for x in texts.values())]:
        assert pii.base_spans(t) == plain_base(t)


def test_pii_linear_on_long_runs():
    assert pii.base_spans("1" * 200_000 + " " + "a" * 200_000 + "@ b") == []


def test_pii_field_accuracy_and_skip_edges():
    w, pair = pii.default_model()
    held = pii.labelled_texts(150, 77)
    score = {}
    for skip in (True, False):
        g = pii.graph_of([x for x, _ in held], skip)
        y = np.array([held[d][1][i] for d, i in g.where])
        p, _ = pii.beliefs(g.matrix() @ w, *g.edges(), pair)
        score[skip] = (p.argmax(1) == y).mean()
    assert score[True] > 0.99 and score[True] > score[False]


def test_pii_exact_on_trees():
    r = np.random.default_rng(1)
    u, pair = r.normal(size=(4, 3)), r.normal(size=(2, 3, 3))
    pair = pair + pair.transpose(0, 2, 1)
    a, b, k = np.array([0, 1, 1]), np.array([1, 2, 3]), np.array([0, 1, 0])
    one, _ = pii.beliefs(u, a, b, k, pair, 60)
    z = np.zeros((4, 3))
    for s in np.ndindex(3, 3, 3, 3):
        z[range(4), s] += np.exp(sum(u[i, s[i]] for i in range(4)) + sum(pair[t][s[x], s[y]] for x, y, t in zip(a, b, k, strict=True)))
    assert np.allclose(one, z / z.sum(1, keepdims=True), atol=1e-5)


def test_pii_query(spark, sf, texts):
    for r in registry.queries()["op1_pii"](spark, sf).collect():
        base = plain_base(texts[r.doc_id] or "")
        joined = ",".join(f"{pii.KINDS[k]}:{a}:{z}" for a, k, z in base)
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest() and set(filter(None, joined.split(","))) <= set(r.spans.split(","))
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == j for _, k, _ in base) for j in range(4))


# --- 2


def test_pieces_equal_library(texts):
    import public_tokenizers
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    r = random.Random(3)
    made = ["".join(r.choice("abcdehilnoprst  ▁\nüß漢") for _ in range(r.randint(0, 300))) for _ in range(150)]
    made += [x or "" for x in ODD] + ["x" * 900, " " * 300 + "é", "abc" * 200 + "  " + "the" * 200] + [t or "" for t in texts.values()][:80]
    code = pieces.PieceCoder()
    ids, n = code.encode(made)
    at = np.concatenate([[0], np.cumsum(n)])
    for i, t in enumerate(made):
        own = ids[at[i] : at[i + 1]].tolist()
        assert own == sp.encode(t) and code.decode(own) == (t if pieces.SPACE not in t else t.replace(pieces.SPACE, " "))


def test_suffix_array():
    r = random.Random(4)
    text = np.array([r.randrange(1, 4) for _ in range(400)])
    order = pieces.suffix_array(text, 400)
    s = "".join(map(str, text))
    assert [s[i:] for i in order] == sorted(s[i:] for i in range(400))


# --- 3


def test_licenses_inherit(spark):
    rows = [(1, "a/LICENSE", "Released under the MIT License."), (2, "a/x.txt", "no"), (3, "a/b/y.txt", None), (4, "c/z.txt", "x"), (5, "a/b/LICENSE.md", "Licensed under the Apache License, Version 2.0."), (6, "a/b/c/d.txt", "hm"), (7, "top.txt", "Foo\nThis work is licensed under the GNU General Public License, version 3.\nBar"), (8, None, "")]
    got = {r.doc_id: (r.license, r.basis, r.license_dir) for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, path string, text string")).collect()}
    assert got == {1: ("MIT", "header", None), 2: ("MIT", "directory", "a"), 3: ("Apache-2.0", "directory", "a/b"), 4: (None, "none", None), 5: ("Apache-2.0", "header", None), 6: ("Apache-2.0", "directory", "a/b"), 7: ("GPL-3.0", "header", None), 8: (None, "none", None)}


# --- 4


def test_word_coder_equals_library(texts):
    code = packing.WordCoder()
    made = [x or "" for x in ODD] + ["ΑΣ σ Σ", "it's 'S 'LL ''s", "x\x85y z\xa0w", "<|endoftext|> hi", "½ ² ẞ ﬃ", "a b　c \x1c"] + [t or "" for t in texts.values()][:80]
    for t, ids in zip(made, code.encode(made), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == code.model.encode(t, add_special_tokens=False).ids


def test_cuts_are_harmonic():
    for n in range(1, 5000, 7):
        parts = packing.cuts(n)
        assert sum(x for x, _ in parts) == n and all(2048 // (k + 1) < x <= 2048 // k for x, k in parts)


def check_packing(rows, texts):
    """Every id once, gapless sequences within capacity; returns the share of real tokens."""
    code, seqs, docs = packing.WordCoder(), defaultdict(list), defaultdict(list)
    for r in rows:
        seqs[r.sequence_id].append((r.offset, r.length))
        docs[r.doc_id].append(r)
    for parts in seqs.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 2048
    assert set(docs) == set(texts)
    for d, parts in docs.items():
        ids, at = code.encode([texts[d] or ""])[0] + b"\1\0\0\0", 0
        for r in sorted(parts, key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) // 4 and r.ids_crc32 == zlib.crc32(ids[4 * at : 4 * (at + r.length)])
            at += r.length
        assert at == len(ids) // 4
    return sum(n for p in seqs.values() for _, n in p) / (2048 * len(seqs))


def test_packing_query(spark, sf, texts):
    assert check_packing(registry.queries()["op4_packing"](spark, sf).collect(), texts) > 0.97


# --- 5


@pytest.mark.parametrize("split", [700, 5000, 1 << 20])
def test_warc_round_trip(spark, split, tmp_path):
    r = random.Random(5)
    html = [None, "", "same", "same", "<p>\x1f\x8b\x08 no</p>", "é" * 3000, *("<p>" + "".join(r.choice("abc <>") for _ in range(r.randint(1, 4000))) + "</p>" for _ in range(40)), "same"]
    pages = spark.createDataFrame([(i, f"http://x/{i} y", h) for i, h in enumerate(html)], "page_id long, url string, html string").repartition(3)
    files = warc.write_archives(pages, f"file://{tmp_path}/w")
    got = {int(x.record_id): x for x in warc.read_archives(spark, [(f.path, f.bytes) for f in files], f"file://{tmp_path}/w", split).collect()}
    first: dict = {}
    for i, h in enumerate(html):
        data = (h or "").encode()
        first.setdefault(data, i)
        x = got[i]
        assert x.payload_bytes == len(data) and x.payload_digest == base64.b32encode(hashlib.sha1(data).digest()).decode()
        assert (x.record_type, x.refers_to_id) == (("response", None) if first[data] == i else ("revisit", str(first[data])))
        assert bytes(x.payload) == (data if first[data] == i else b"")
    assert len(got) == len(html)


def test_warc_empty(spark, tmp_path):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    files = warc.write_archives(pages, f"file://{tmp_path}/e")
    assert warc.read_archives(spark, [(f.path, f.bytes) for f in files], f"file://{tmp_path}/e").count() == 0


# --- 6


def test_passages_found_and_clean_left(spark):
    passage, fuzzy = prose(70, 1), prose(120, 2).split()
    near = [w if i % 11 else "changed" for i, w in enumerate(fuzzy)]
    rows = [(0, prose(200, 10) + " " + passage + " " + prose(90, 11)), (1, prose(90, 12) + " " + passage + " " + prose(50, 13)), (2, prose(300, 14)), (3, prose(60, 15) + " " + " ".join(fuzzy) + " " + prose(30, 16)), (4, prose(40, 17) + " " + " ".join(near)), (5, prose(80, 18)), (6, prose(80, 18)), (7, prose(30, 19) + " " + " ".join(passage.split()[:20]))]
    text = dict(rows)
    got = passages.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {(r.doc_id, r.source_id) for r in got} == {(1, 0), (4, 3), (6, 5)}
    one = next(r for r in got if r.doc_id == 1)
    assert text[1][one.start : one.end] == passage == text[0][one.source_start : one.source_end]


def test_passages_whose_parts_stand_in_smaller_documents(spark):
    for n in (50, 51, 60, 75, 98):
        p = prose(n, n, 10**6).split()
        third, half = n // 3, n // 2
        rows = [(0, prose(40, 40, 10**6) + " " + " ".join(p[:half])), (1, " ".join(p[half:]) + " " + prose(40, 41, 10**6)), (2, prose(30, 42, 10**6) + " " + " ".join(p)), (3, " ".join(p[third : n - 5]) if n - 5 - third < 50 else prose(60, 46, 10**6)), (4, " ".join(p) + " " + prose(30, 43, 10**6))]
        text, got = dict(rows), passages.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
        assert {(r.doc_id, r.source_id, text[r.doc_id][r.start : r.end]) for r in got} == {(4, 2, " ".join(p))}


def test_passages_all_places_in_a_document(spark):
    p, often = prose(60, 70, 10**6), [prose(9, 71 + i, 10**6) for i in range(3)]
    p = " ".join(x for i, x in enumerate(p.split()) for x in ([x, *often[i // 20].split()] if i % 20 == 9 else [x]))
    alone = " ".join(prose(12, 80 + i, 10**6) + " " + x for i, x in enumerate(often))
    rows = [(0, prose(30, 90, 10**6) + " " + p), (1, alone + " " + prose(20, 91, 10**6) + " " + p + " " + prose(25, 92, 10**6) + " " + p + " " + prose(20, 93, 10**6) + " " + p)]
    text, got = dict(rows), passages.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert [text[1][r.start : r.end] for r in got] == [p] * 3 and len({r.start for r in got}) == 3


def test_passages_every_run_is_covered(spark):
    r = random.Random(60)
    pool = [prose(r.randint(8, 90), 100 + i, 10**6) for i in range(14)]
    rows = [(i, " ".join(x for _ in range(r.randint(1, 7)) for x in (r.choice(pool), prose(r.randint(0, 12), r.randrange(10**6), 10**6)))) for i in range(60)]
    seen, covered = {}, defaultdict(list)
    for x in passages.passages(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect():
        assert x.source_id < x.doc_id
        covered[x.doc_id].append((x.start, x.end))
    missed = 0
    for d, t in rows:
        w = [m.span() for m in re.finditer(WORD, t)]
        for i in range(len(w) - 49):
            run = tuple(t[a:z] for a, z in w[i : i + 50])
            if seen.setdefault(run, d) != d:
                missed += not any(a <= w[i][0] and w[i + 49][1] <= z for a, z in covered[d])
    assert missed == 0


def test_passage_links_do_not_depend_on_batches():
    r = random.Random(61)
    texts = [" ".join(prose(r.randint(20, 70), r.randrange(4), 10**6) for _ in range(3)) for _ in range(30)]

    class Docs:
        def mapInArrow(self, run, _):  # noqa: N802
            return pa.Table.from_batches(run([pa.RecordBatch.from_arrays([pa.array(range(30)), pa.array(texts)], names=["doc", "t"])]))

    found = passages.seeds(Docs()).sort_by([("h", "ascending"), ("doc", "ascending"), ("pos", "ascending")]).combine_chunks()
    got = [{x for b in passages._linked(found.to_batches(max_chunksize=n)) for x in zip(*(c.to_pylist() for c in b.columns), strict=True)} for n in (10**6, 7, 1)]
    assert got[0] and all(x[:2] in {y[:2] for y in got[0]} for x in got[2])
    assert {x[:2] for x in got[0]} == {x[:2] for x in got[1]} == {x[:2] for x in got[2]}


def test_passages_edited_whose_seeds_have_other_holders(spark):
    p = prose(120, 50, 10**6).split()
    parts = [" ".join(p[i : i + 24]) for i in range(0, 100, 4)]
    edited = " ".join(w if i % 24 != 23 else "changed" for i, w in enumerate(p))
    alone = lambda first, seed: [(first + i, f"{prose(40, seed + i, 10**6)} {x} {prose(40, seed + 500 + i, 10**6)}") for i, x in enumerate(parts)]
    rows = [*alone(0, 2000), (100, prose(30, 51, 10**6) + " " + edited), *alone(200, 4000), (300, " ".join(p) + " " + prose(30, 52, 10**6))]
    got = passages.passages(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert {(r.doc_id, r.source_id) for r in got} == {(300, 100)}
    assert min(r.start for r in got) == 0 and max(r.end for r in got) >= len(" ".join(p[:119]))


def test_passages_against_all_pairs(spark):
    r = random.Random(62)
    pool = [prose(r.randint(70, 160), 700 + i, 10**6).split() for i in range(8)]

    def piece(w):
        n = r.choice([22, 30, 44, 90])
        at = r.randrange(max(1, len(w) - n))
        rate = r.choice([0, 0.03, 0.08])
        return [x for x in w[at : at + n] for x in ([x] if r.random() > rate else r.choice([[], ["new"], [x, "more"]]))]

    made = [" ".join(x for _ in range(r.randint(1, 4)) for x in (*piece(r.choice(pool)), *prose(r.randint(5, 40), r.randrange(10**6), 10**6).split())) for _ in range(120)]
    rows = list(enumerate(made))
    covered = defaultdict(list)
    for x in passages.passages(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect():
        covered[x.doc_id].append((x.start, x.end))
    words = Words(pa.array(made))
    of = [(words.hash[a:z] >> np.uint64(32)).astype(np.uint32) for a, z in zip(words.first, words.first[1:], strict=False)]
    held = [defaultdict(list) for _ in made]
    for h, at in zip(*passages.minimizers(words), strict=True):
        held[words.doc[at]][h].append(int(at - words.first[words.doc[at]]))
    pairs = missed = 0
    for d, t in rows:
        span = [m.span() for m in re.finditer(WORD, t)]
        for s in range(d):
            both = [(b, held[s][h][0 if first else min(k, len(held[s][h]) - 1)]) for h in held[d].keys() & held[s].keys() for k, b in enumerate(held[d][h]) for first in (0, 1)]
            for bs, as_, b_lo, b_hi, a_lo, a_hi in passages._promising([b for b, _ in both], [a for _, a in both]):
                b0, b1, a0, a1, equal = passages.align([b - b_lo for b in bs], [a - a_lo for a in as_], of[d][b_lo:b_hi], of[s][a_lo:a_hi])
                if b1 - b0 >= 50 and equal >= 0.8 * max(b1 - b0, a1 - a0):
                    pairs += 1
                    missed += sum(not any(x <= span[b][0] and span[b + 4][1] <= y for x, y in covered[d]) for b in bs)
    assert pairs > 100 and missed == 0


def test_passages_runs_of_repeated_words_are_covered(spark):
    r = random.Random(64)
    rows = [(i, " ".join(x for _ in range(r.randint(2, 5)) for x in (*[r.choice(["the", "of"])] * r.choice([20, 55, 63, 110, 170]), *prose(r.randint(1, 9), r.randrange(10**6), 10**6).split()))) for i in range(40)]
    covered, seen, need = defaultdict(list), {}, 0
    for x in passages.passages(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect():
        covered[x.doc_id].append((x.start, x.end))
    for d, t in rows:
        w = [m.span() for m in re.finditer(WORD, t)]
        for i in range(len(w) - 49):
            if seen.setdefault(tuple(t[a:z] for a, z in w[i : i + 50]), d) != d:
                need += 1
                assert any(a <= w[i][0] and w[i + 49][1] <= z for a, z in covered[d])
    assert need > 1000


def test_passages_of_a_common_stretch_are_not_paired_with_all_its_holders(spark):
    stretch, after = prose(36, 65, 10**6), prose(30, 66, 10**6).split()
    goes_on = {7: " ".join(after), 40: " ".join(["changed", *after[1:]])}
    rows = [(i, f"{prose(40, 5000 + i, 10**6)} {x} {goes_on.get(i, '')} {prose(40, 6000 + i, 10**6)}") for i in range(60) for x in (stretch if i % 2 else " ".join(["of"] * (20 + i // 2)),)]
    rows[40] = (40, f"{prose(40, 5040, 10**6)} {stretch} {goes_on[40]} {prose(40, 6040, 10**6)}")
    texts = spark.createDataFrame(rows, "doc long, t string")
    got = passages._left_open(texts, spark.createDataFrame([], passages.FOUND), 3).collect()
    assert {(x.doc, x.src) for x in got} == {(40, 7)}


def test_passage_words_around_a_seed_large_groups_as_small_ones():
    r = random.Random(67)
    base = [r.randrange(30) for _ in range(128)]

    def around():
        left, right = r.randint(0, 30), r.randint(5, 30)
        w = [x if 64 - left <= i < 64 + right or (r.random() < 0.8 and i % 7) else r.randrange(30) for i, x in enumerate(base)][r.choice([0, 20, 50]) :]
        return np.uint32(len(w) - 64).tobytes() + np.array(w, np.uint32).tobytes()

    words = [around() for _ in range(150)]
    doc, loose = np.arange(150) // 2, np.array([r.random() < 0.6 for _ in range(150)])
    small, large = ({(int(a), int(b)) for x, y in passages._going_on(doc, loose, words, n) for a, b in zip(x, y, strict=True)} for n in (10**6, 0))
    of = [np.frombuffer(w, np.uint32) for w in words]
    need = set()
    for x in range(150):
        for y in range(150):
            sides = [(w[1 : 1 + w[0]][::-1], w[1 + w[0] :]) for w in (of[x], of[y])]
            verbatim = sum(next((i for i, (u, v) in enumerate(zip(a, b, strict=False)) if u != v), min(len(a), len(b))) for a, b in zip(*sides, strict=True))
            if loose[x] and doc[y] < doc[x] and verbatim < 50 and sum(passages.reach(a, b)[0] for a, b in zip(*sides, strict=True)) >= 50:
                need.add((x, y))
    assert len(need) > 20 and need <= large <= small


def test_passage_ranks_and_islands_do_not_depend_on_batches():
    r = random.Random(63)
    rows = sorted({(r.randrange(40), r.randrange(12), 7, r.randrange(3)) for _ in range(400)})
    table = pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int32()), strict=True)], names=["h", "doc", "t", "pos"])
    held = defaultdict(set)
    for h, d, _, _ in rows:
        held[h].add(d)
    want = sorted((d, t, p, min(2, sum(x < d for x in held[h])), h) for h, d, t, p in rows if len(held[h]) > 1)
    for n in (10**6, 7, 1):
        ranked = pa.Table.from_batches(passages._ranked(table.to_batches(max_chunksize=n)))
        assert sorted(zip(*(c.to_pylist() for c in ranked.columns), strict=True)) == want
    ranked = ranked.sort_by([(c, "ascending") for c in ("doc", "t", "pos", "rank")]).combine_chunks()
    islands = [[x.as_py() for b in passages._islands(ranked.to_batches(max_chunksize=n)) for x in b.to_struct_array()] for n in (10**6, 7, 1)]
    assert islands[0] and islands[0] == islands[1] == islands[2]


def test_passages_against_all_windows(spark, sf, docs, texts):
    held = defaultdict(set)
    for d, t in texts.items():
        w = re.findall(WORD, t or "")
        for i in range(len(w) - 50):
            held[tuple(w[i : i + 51])].add(d)
    need = {d for s in held.values() if len(s) > 1 for d in s - {min(s)}}
    assert need <= {r.doc_id for r in registry.queries()["op6_passages"](spark, sf).collect()}


def test_chains_are_collinear():
    r = random.Random(6)
    for _ in range(60):
        pts = sorted({(r.randrange(60), r.randrange(60)) for _ in range(25)})
        b, a = [x for x, _ in pts], [y for _, y in pts]
        used = [i for c in passages.chains(b, a) for i in c]
        assert len(used) == len(set(used)) == len(pts)
        for c in passages.chains(b, a):
            assert all(b[x] < b[y] and a[x] < a[y] for x, y in zip(c, c[1:], strict=False))


# --- 7


def plain_similar(texts, least=0.8):
    sets = {}
    for d, t in texts.items():
        w = re.findall(WORD, t or "")
        sets[d] = frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()
    top = {d: d for d in texts}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    inverted, links = defaultdict(list), defaultdict(set)
    for d, s in sets.items():
        for g in s:
            inverted[g].append(d)
    pairs = {(x, y) for v in inverted.values() for i, x in enumerate(v) for y in v[i + 1 :]}
    pairs |= {(x, y) for x in texts for y in texts if x < y and (texts[x] or "") == (texts[y] or "")}
    for x, y in pairs:
        same, k = (texts[x] or "") == (texts[y] or ""), len(sets[x] & sets[y])
        if same or k and k >= least * (len(sets[x]) + len(sets[y]) - k) - 1e-9:
            p, q = sorted((find(x), find(y)))
            top[q] = p
            if not same:
                links[x].add(texts[y])
                links[y].add(texts[x])
    return {d: (find(d), len(links[d])) for d in texts}


def test_jaccard_against_all_pairs(spark, sf, texts):
    got = {r.doc_id: (r.class_id, r.n_links) for r in registry.queries()["op7_jaccard"](spark, sf).collect()}
    assert got == plain_similar(texts)


def test_jaccard_large_group_in_blocks(spark):
    r, base = random.Random(7), prose(160, 30).split()
    rows = [(i, " ".join(w if j != i % 150 else f"own{i}" for j, w in enumerate(base))) for i in range(230)] + [(500, prose(150, 31)), (501, "tiny text"), (502, "tiny text")]
    r.shuffle(rows)
    got = {x.doc_id: (x.class_id, x.n_links) for x in jaccard.similar(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == plain_similar(dict(rows))


def test_runs_for_recall():
    assert jaccard.runs_for(0.999) == 3 and jaccard.runs_for(0.9) == 1


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 1000 + i) for i in range(1, 40)] + [(7, 7)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert all(got[i] == 0 for i in range(61)) and all(got[1000 + i] == 1000 for i in range(40))


# --- 8


@pytest.mark.parametrize("lacing", ["fixed", "xiph", "ebml", "none"])
@pytest.mark.parametrize("n", [0, 1, 576, 577, 576 * 9, 576 * 130 + 5])
def test_matroska_round_trip(lacing, n):
    payload = matroska.padded(bytes(random.Random(n).randrange(256) for _ in range(n)))
    media = matroska.write(payload, lacing=lacing)
    seen = matroska.parse(media)
    assert b"".join(media[a:b] for _, _, a, b, _ in seen["packets"]) == payload
    assert [ns for _, ns, *_ in seen["packets"]] == [k * 72_000_000 for k in range(len(payload) // 576)]
    assert seen["cues"] and all(media[c : c + 4] == b"\x1f\x43\xb6\x75" for _, _, c in seen["cues"]) and seen["tracks"][1]["codec"] == "A_PCM/INT/LIT"


def test_matroska_variable_lacing_groups_and_truncation():
    r = random.Random(8)
    frames = [bytes(r.randrange(256) for _ in range(r.randint(1, 900))) for _ in range(9)]
    for how, flag in (("xiph", 2), ("ebml", 6)):
        block = matroska.element(matroska.GROUP, matroska.element(matroska.BLOCK, b"\x81\0\0" + bytes([flag]), matroska.lace(frames, how)), matroska.number(matroska.REFERENCE, 1))
        body = matroska.number(matroska.TIMECODE, 5) + block
        data = b"\x18\x53\x80\x67\x01\xff\xff\xff\xff\xff\xff\xff" + b"\x1f\x43\xb6\x75\xff" + body + b"\x1f\x43\xb6\x75\xff" + body
        got = matroska.parse(data)["packets"]
        assert [data[a:b] for _, _, a, b, _ in got] == frames * 2 and not any(k for *_, k in got)
        for cut in range(0, len(data), 97):
            matroska.parse(data[:cut])


def test_matroska_query(spark, sf, texts):
    for r in registry.queries()["op8_matroska"](spark, sf).collect():
        data = (texts[r.doc_id] or "").encode()
        p = data + b"\xff" * ((-len(data)) % 576 or (576 if not data else 0))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(data), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]))
    small = spark.createDataFrame([(1, "abc"), (2, "abc")], "doc_id long, text string")
    assert matroska.packet_table(matroska.store(small)).count() == 2


# --- 9


def test_html_held_out_blocks():
    model, hit, said, want = htmltext.default_model(), 0, 0, 0
    for source, blocks in htmltext.labelled_pages(120, 98):
        a, b = Counter(htmltext.extract(source, model).split("\n")), Counter(blocks)
        hit, said, want = hit + sum((a & b).values()), said + sum(a.values()), want + sum(b.values())
    assert hit / said > 0.97 and hit / want > 0.95


def test_html_messages_are_exact():
    page = htmltext.Page("<div><p>a<b>c</b></p><ul><li>x</ul></div>")
    r = np.random.default_rng(2)
    u, pair = r.normal(size=(len(page.tag), 2)), r.normal(size=(2, 2, 2))
    z = np.zeros((len(page.tag), 2))
    for s in np.ndindex(*(2,) * len(page.tag)):
        z[range(len(s)), s] += np.exp(sum(u[i, s[i]] for i in range(len(s))) + sum(pair[page.kinds()[i]][s[page.parent[i]], s[i]] for i in range(1, len(s))))
    want = z[:, 1] / z.sum(1)
    assert np.allclose(htmltext.marginals(page, u, pair), want)
    assert np.allclose(htmltext.sum_product(np.array(page.parent), np.array(page.kinds()), u, pair)[1][:, 1], want)


def test_html_query_and_odd_pages(spark, sf):
    import html

    for r in registry.queries()["op9_htmltext"](spark, sf).join(spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html"), "page_id").collect():
        article = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        want = [" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h\d|ul|li|div)\b[^>]*>", article)]
        assert r.text == "\n".join(filter(None, want)) and r.n_chars == len(r.text)
    odd = spark.createDataFrame([(1, None, None), (2, "u", ""), (3, "u", "<"), (4, "u", "plain & text"), (5, "u", "<p>a<p" + "<div>" * 3000)], "page_id long, url string, html string").withColumn("h", __import__("pyspark").sql.functions.lit(1))
    assert [r.text for r in htmltext.main_text(odd).orderBy("page_id").collect()][:2] == ["", ""]


# --- 10


def plain_counts(t):
    t = t or ""
    w, seen, dup, mark = re.findall(WORD, t), set(), 0, set()
    for line in t.split("\n"):
        if re.search(WORD, line):
            dup += line in seen
            seen.add(line)
    grams = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    for i in range(len(w) - 7):
        if grams[tuple(w[i : i + 8])] > 1:
            mark.update(range(i, i + 8))
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(mark)


def test_quality_base_counts(texts):
    r = random.Random(9)
    made = ["".join(r.choice("ab#\n \té|") for _ in range(r.randint(0, 120))) for _ in range(300)] + [x or "" for x in ODD] + [t or "" for t in texts.values()]
    got = quality.base_counts(Words(pa.array(made)))
    assert list(zip(*(got[c].tolist() for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), strict=True)) == [plain_counts(t) for t in made]


def test_quality_model_both_ways(spark, docs):
    some = docs.where("doc_id < 25")
    a, b = ({r.doc_id: (round(r.bits or 0, 6), r.kept) for r in quality.judge(some, most=m).collect()} for m in (quality.MOST_ENTRIES, 0))
    assert a == b


def test_quality_model_both_ways_on_repeated_and_null_ids(spark, docs):
    rows = [(r.doc_id // 2 if r.doc_id % 5 else None, r.text, r.lang) for r in docs.where("doc_id < 24").collect()]
    some = spark.createDataFrame([*rows, *rows[:8], rows[3], (None, "", "en"), (1, None, None)], "doc_id long, text string, lang string")
    a, b = (Counter((r.doc_id, r.n_bytes, r.bits if r.bits is None else round(r.bits, 6), r.kept) for r in quality.judge(some, most=m).collect()) for m in (quality.MOST_ENTRIES, 0))
    assert a == b and sum(a.values()) == some.count()


def test_kneser_ney_sums_to_one(spark, docs):
    model = quality.Model.from_counts(quality.ngram_counts(docs.where("doc_id < 25")).toArrow())
    keys = model.of["en", quality.ORDER][0]
    for key in keys[len(keys) // 2 :: 500][:5]:
        probs = np.exp(model.logp("en", np.array([(key >> 8 << 8) | c for c in range(256)])))
        assert abs(probs.sum() - 1) < 1e-3


def test_quality_keeps_clean_and_rejects_noise(spark):
    r = random.Random(10)
    clean = [(i, " ".join(r.choice(["the", "house", "stands", "near", "a", "river", "and", "old", "trees", "grow"]) + r.choice(["", "s", "ly"]) for _ in range(120)), "en") for i in range(60)]
    noise = [(100 + i, "".join(chr(r.randrange(0x400, 0x2000)) + (" " if r.random() < 0.2 else "") for _ in range(400)), "en") for i in range(3)]
    got = {x.doc_id: x.kept for x in quality.judge(spark.createDataFrame(clean + noise, "doc_id long, text string, lang string")).collect()}
    assert all(got[i] for i, *_ in clean) and not any(got[i] for i, *_ in noise)


def test_quality_rejects_symbol_junk_and_short_noise(spark, sf):
    docs = spark.read.parquet(f"{sf[:-5]}0.01/documents.parquet").select("doc_id", "text", "lang")
    r = random.Random(11)
    noise = [(10**6 + i, " ".join("".join(chr(r.randrange(0x400, 0x2000)) for _ in range(2)) for _ in range(24)), "en") for i in range(4)]
    assert all(len(t.encode()) < 200 for _, t, _ in noise)
    got = [x for x in quality.judge(docs.union(spark.createDataFrame(noise, "doc_id long, text string, lang string"))).collect() if not x.base_failed]
    symbols = [x.kept for x in got if x.n_symbols * 50 > x.word_chars and x.doc_id < 10**6]
    clean = [x.kept for x in got if x.n_symbols * 50 <= x.word_chars and x.doc_id < 10**6]
    assert not any(x.kept for x in got if x.doc_id >= 10**6)
    assert sum(symbols) <= 0.7 * len(symbols) and sum(clean) >= 0.98 * len(clean)


def test_written_tables_survive(spark):
    df = written(spark.range(5), "x")
    assert df.count() == 5 and "Scan parquet" in df._jdf.queryExecution().toString()
