"""Fuzzy repeated passages across documents by collinear chaining.

Seeds are the window minimizers of `K`-word shingles, so a run of K + WINDOW - 1 common words always shares one. Every
occurrence of a seed is linked to the smallest document that holds it and to the last one before its own, never to all
others; and every run of `MIN_WORDS` words to the smallest document that holds all of it, so that no verbatim passage is
lost to documents that hold its parts. What these links leave open is linked to smaller holders: a seed outside the
passages found so far, in a stretch of shared seeds of which one has more than two holders, meets the stretches with which
it shares more than the words alike around it: another seed of its neighbourhood with other words between, or words that
go on alike. The two stretches are chained by all the seeds they share. The links of two documents are chained in order, with a gap cost, by a Fenwick
tree of best scores over the source's positions; chains are aligned word by word between and beyond their anchors, and
those of at least `MIN_WORDS` words and `IDENTITY` are passages of the later document that the earlier one holds.

Defined results: null text is an empty one; documents without a repeated passage have no row; of exact copies each
but the smallest id has one row for the whole text (if that has MIN_WORDS words); a passage inside another one of its
document has no row, and of equal ones that with the smallest source stays; rows of one id are one document, whose
passages are told apart by the MD5 of the text that holds them, and equal rows count once; null ids have no passages
and are no sources; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from .common import Words, _powers_for, mix, ready, slices, table, written

K, WINDOW, MIN_WORDS, IDENTITY = 5, 16, 50, 0.8
MARGIN, STEP, MAX_GAP, MAX_SHIFT, GAP_COST = 64, 32, 64, 24, 0.02
_TOP = np.uint64(0xFFFFFFFFFFFFFFFF)


def minimizers(words: Words, k: int = K, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(hash, index of its first word) of the shingles that are the least of some window inside their text."""
    gram, at = words.grams(k)
    n = len(gram)
    if not n:
        return gram, at
    doc = words.doc[at]
    low = np.concatenate([gram, np.full(window, _TOP)])
    span = 1
    while span * 2 <= window:
        low = np.minimum(low[: len(low) - span], low[span:])
        span *= 2
    if span < window:
        low = np.minimum(low[: len(low) - (window - span)], low[window - span :])
    low = low[:n].copy()
    ends = np.minimum(np.arange(n) + window - 1, n - 1)
    low[(doc[ends] != doc) | (np.arange(n) + window > n)] = 0  # windows that a text's end cuts choose nothing
    high = np.concatenate([np.zeros(window - 1, np.uint64), low])
    span = 1
    while span * 2 <= window:
        high = np.maximum(high[: len(high) - span], high[span:])
        span *= 2
    if span < window:
        high = np.maximum(high[: len(high) - (window - span)], high[window - span :])
    chosen = np.flatnonzero(high[:n] == gram)
    return gram[chosen], at[chosen]


def least_at(x: np.ndarray, window: int) -> np.ndarray:
    """Index of the first least value of each x[i : i + window]."""
    at, span = np.arange(len(x)), 1
    while span < window:
        step = min(span, window - span)
        left, right = at[: len(at) - step], at[step:]
        at = np.where(x[right] < x[left], right, left)
        span += step
    return at


def seeds(docs):
    """h, doc, pos, off, w: each document's minimizers, and 32-bit hashes of the runs of MIN_WORDS words whose least shingle they are.

    The run i of w begins at word pos - off + i. Equal runs have equal shingles, so their hashes come with the same h.
    """

    def run(batches):
        for part in slices(batches, "t"):
            words = Words(part.column(1))
            gram, at = minimizers(words)
            doc = words.doc[at]
            long, begin = words.grams(MIN_WORDS)
            bounds, off = np.zeros(len(at) + 1, np.int64), np.zeros(len(at), np.int64)
            if len(long):
                every, word = words.grams(K)
                own = word[least_at(every, MIN_WORDS - K + 1)[np.searchsorted(word, begin)]]  # ascending, as begin is
                bounds[:-1], bounds[-1] = np.searchsorted(own, at), len(own)
                off = at - begin[np.minimum(bounds[:-1], len(begin) - 1)]
            w = pa.Array.from_buffers(pa.binary(), len(at), [None, pa.py_buffer((4 * bounds).astype(np.int32)), pa.py_buffer((long >> np.uint64(32)).astype(np.uint32))])
            yield pa.RecordBatch.from_arrays([pa.array(gram.view(np.int64)), part.column(0).take(pa.array(doc)), pa.array((at - words.first[doc]).astype(np.int32)), pa.array(off.astype(np.int32)), w], names=["h", "doc", "pos", "off", "w"])

    return docs.mapInArrow(run, "h long, doc long, pos int, off int, w binary")


def _new(*columns: np.ndarray) -> np.ndarray:
    """Where the rows of sorted columns differ from the ones before."""
    out = np.ones(len(columns[0]), bool)
    if len(out):
        out[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    return out


def _runs(group: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows sorted by group and doc: the run (equal group and doc) of each row, the runs' bounds, the first run of each
    run's group, and the row's number in its run."""
    begins = np.flatnonzero(_new(group, doc))
    run = np.cumsum(_new(group, doc)) - 1
    bounds = np.append(begins, len(group))
    heads = np.flatnonzero(_new(group[begins])) if len(begins) else begins
    head = heads[np.searchsorted(heads, np.arange(len(begins)), "right") - 1] if len(begins) else heads
    return run, bounds, head, np.arange(len(group)) - bounds[run]


def _links(h, doc, pos, off, words, size, fresh):
    """Anchors (doc, src, pos, at, 0) of the rows `fresh`, sorted by h, doc, pos; and which rows' runs of words are first of their kind.

    A seed is linked to the smallest document that holds it and to the one before its own, there to the first and to
    the occurrence of the same number. A run of MIN_WORDS words is linked to the smallest that has it, whose occurrences
    are taken in turn; runs that follow each other in both are one row, with their words instead of the 0.
    """
    run, bounds, head, k = _runs(h, doc)
    x, y = [], []
    for to in (head, np.maximum(head, np.arange(len(head)) - 1)):
        rows = np.flatnonzero(fresh & (to[run] < run))
        first, n = bounds[to[run[rows]]], np.diff(bounds)[to[run[rows]]]
        x += [rows, rows]
        y += [first, first + np.minimum(k[rows], n - 1)]
    x, y = np.concatenate(x), np.concatenate(y)
    out = [np.stack([doc[x], doc[y], pos[x], pos[y], np.zeros(len(x), np.int64)])]
    row = np.repeat(np.arange(len(h)), size)
    begin = pos[row] - off[row] + np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
    group = np.cumsum(_new(h))[row]
    order = np.lexsort((begin, doc[row], words, group))
    row, begin, group, word = row[order], begin[order], group[order], words[order]
    key = np.cumsum(_new(group, word)) if len(row) else group
    run, bounds, head, k = _runs(key, doc[row])
    rows = np.flatnonzero(fresh[row] & (head[run] < run)) if len(row) else row
    to = bounds[head[run[rows]]]
    to = to + k[rows] % np.diff(bounds)[head[run[rows]]]
    least = np.zeros(len(words), bool)
    least[order] = head[run] == run if len(row) else False
    if len(rows):
        shift = begin[to] - begin[rows]
        pair = np.lexsort((begin[rows], shift, row[to], row[rows]))
        edge = _new(row[rows][pair], row[to][pair], shift[pair])
        edge[1:] |= np.diff(begin[rows][pair]) > 1
        last = pair[np.append(edge[1:], True)]
        rows, to, last = rows[pair[edge]], to[pair[edge]], rows[last]
        out.append(np.stack([doc[row[rows]], doc[row[to]], begin[rows], begin[to], begin[last] - begin[rows] + MIN_WORDS]))
    out = np.concatenate(out, 1)
    out = out[:, np.lexsort(out[::-1])]
    return out[:, _new(*out)], least


def _linked(batches):
    """Rows (h, doc, pos, off, w) sorted by h, doc, pos: their anchors. Of an open group only what later rows need is held."""
    none = lambda t: np.zeros(0, t)
    held = [none(np.int64), none(np.int64), none(np.int64), none(np.int64), none(np.uint32), none(np.int64)]
    for batch in batches:
        if not batch.num_rows:
            continue
        w = batch.column(4)
        bounds = np.frombuffer(w.buffers()[1], np.int32)[w.offset : w.offset + len(w) + 1].astype(np.int64)
        data = w.buffers()[2]
        data = np.frombuffer(data, np.uint8)[bounds[0] : bounds[-1]].view(np.uint32) if data is not None and bounds[-1] > bounds[0] else none(np.uint32)
        rows = [*(batch.column(i).to_numpy().astype(np.int64) for i in range(4)), data, np.diff(bounds) // 4]
        h, doc, pos, off, words, size = (np.concatenate([a, b]) for a, b in zip(held, rows, strict=True))
        fresh = np.arange(len(h)) >= len(held[0])
        many = np.zeros(len(h), bool)  # groups of several documents, and the open one
        run, _, head, _ = _runs(h, doc)
        several = np.bincount(head, minlength=len(head)) > 1
        many = several[head[run]]
        of = np.repeat(np.arange(len(h)), size)
        pick = many[of]
        least = np.ones(len(words), bool)
        if many.any():
            got, least[pick] = _links(h[many], doc[many], pos[many], off[many], words[pick], size[many], fresh[many])
            if got.shape[1]:
                yield pa.RecordBatch.from_arrays([pa.array(got[0]), pa.array(got[1]), *(pa.array(x.astype(np.int32)) for x in got[2:])], names=["doc", "src", "pos", "at", "alike"])
        # the last group goes on: its first and its last two documents, and the rows whose runs are first of their kind
        open_ = h == h[-1]
        some = np.zeros(len(h), bool)
        some[of[least]] = True
        keep = open_ & (some | (run == head[run]) | (run >= run[-1] - 1))
        held = [h[keep], doc[keep], pos[keep], off[keep], words[keep[of]], size[keep]]


def chains(b: list[int], a: list[int], k: int = K, cost: float = GAP_COST) -> list[list[int]]:
    """Collinear chains of anchors (b ascending, b[i] in one text and a[i] in the other), best first; each anchor is in one chain at most."""
    n = len(b)
    if all(0 < y - x <= MAX_GAP for x, y in zip(b, b[1:], strict=False)) and len({y - x for x, y in zip(a, b, strict=True)}) == 1:
        return [list(range(n))]
    rank = {x: r for r, x in enumerate(sorted(set(a)), 1)}
    size, score, back = len(rank) + 1, [0.0] * n, [-1] * n
    tree, owner = [float("-inf")] * size, [-1] * size  # a Fenwick tree: best score, and the last anchor that has it, over a prefix of ranks
    at = [rank[x] for x in a]
    i = 0
    while i < n:
        j = i
        while j < n and b[j] == b[i]:
            best, p, r = float("-inf"), -1, at[j] - 1
            while r > 0:
                if tree[r] > best or (tree[r] == best and owner[r] > p):
                    best, p = tree[r], owner[r]
                r -= r & -r
            best -= cost * (b[j] + a[j])
            if best > 0:
                score[j], back[j] = k + best, p
            else:
                score[j] = float(k)
            j += 1
        for m in range(i, j):
            value, r = score[m] + cost * (b[m] + a[m]), at[m]
            while r < size:
                if value >= tree[r]:
                    tree[r], owner[r] = value, m
                r += r & -r
        i = j
    out, used = [], [False] * n
    for end in sorted(range(n), key=lambda x: -score[x]):
        chain, at = [], end
        while at >= 0 and not used[at]:
            if chain and (b[chain[-1]] - b[at] > MAX_GAP or a[chain[-1]] - a[at] > MAX_GAP or abs((b[chain[-1]] - b[at]) - (a[chain[-1]] - a[at])) > MAX_SHIFT):
                break
            used[at] = True
            chain.append(at)
            at = back[at]
        if chain:
            out.append(chain[::-1])
    return out


CHAINS = "doc long, src long, bs array<int>, as array<int>, b_lo int, b_hi int, a_lo int, a_hi int"


def _promising(b: list[int], a: list[int]) -> list[tuple]:
    """The chains (bs, as, b_lo, b_hi, a_lo, a_hi) of two documents' anchors that may become passages, and the words around them to look at."""
    both, out = sorted(set(zip(b, a, strict=True))), []
    b, a = [x for x, _ in both], [y for _, y in both]
    for chain in chains(b, a):
        x, y = [b[i] for i in chain], [a[i] for i in chain]
        if x[-1] + K - x[0] >= MIN_WORDS - 2 * (WINDOW - 1):
            out.append(_bounded(x, y))
    return out


def _bounded(x: list[int], y: list[int]) -> tuple:
    lo, hi = lambda v: max(0, v - MARGIN) // STEP * STEP, lambda v: -(-(v + K + MARGIN) // STEP) * STEP
    return x, y, lo(x[0]), hi(x[-1]), lo(y[0]), hi(y[-1])


def _chain_rows(out: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), [pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32())] + [pa.int32()] * 4, strict=True)], names=[x.split()[0] for x in CHAINS.split(", ")])


def _verbatim(runs: np.ndarray, found: list[tuple]) -> list[tuple]:
    """Runs (rows pos, at, alike) of two documents: chains of those whose ends and diagonal are not in a chain found."""
    pos, at, n = runs
    order = np.lexsort((pos, at - pos))
    pos, shift, n = pos[order], (at - pos)[order], n[order]
    line = np.cumsum(_new(shift)) - 1
    upto = np.maximum.accumulate((line << 32) + pos + n)
    first = np.ones(len(pos), bool)
    first[1:] = (line[1:] << 32) + pos[1:] > upto[:-1]
    last = np.append(first[1:], True)
    whole = list(zip(shift[first].tolist(), pos[first].tolist(), (upto[last] & 0xFFFFFFFF).tolist(), strict=True))
    of = {}
    for shift, x, end in whole:
        of[x, x + shift] = of[end - K, end - K + shift] = None
    for i, chain in enumerate(found):
        if len(of) > 2 * len(chain[0]) or len(found) > 1:
            of.update((p, (i, j)) for j, p in enumerate(zip(*chain[:2], strict=True)) if p in of)
        else:
            for p in of:
                j = bisect.bisect_left(chain[0], p[0])
                if j < len(chain[0]) and (chain[0][j], chain[1][j]) == p:
                    of[p] = i, j
    out = []
    for shift, x, end in whole:
        one, other = of[x, x + shift], of[end - K, end - K + shift]
        if not one or not other or one[0] != other[0] or any(v - u != shift for u, v in zip(*(c[one[1] : other[1]] for c in found[one[0]][:2]), strict=True)):
            out.append(_bounded([x, end - K], [x + shift, end - K + shift]))
    return out


def _chained(batches):
    """Rows (doc, src, pos, at, alike) sorted by doc, src, pos: the chains that may become passages."""
    key, b, a, runs, out = None, [], [], [], []

    def settle():
        found = _promising(b, a)
        out.extend((*key, *x) for x in (found + _verbatim(np.concatenate(runs, 1), found) if runs else found))

    for batch in batches:
        docs, src, pos, at, alike = (batch.column(i).to_numpy() for i in range(5))
        new = _new(docs, src)
        starts = [*np.flatnonzero(new).tolist(), len(docs)]
        for x, y in zip(starts, starts[1:], strict=False):
            now = (int(docs[x]), int(src[x]))
            if now != key:
                if len(b) > 1:
                    settle()
                key, b, a, runs = now, [], [], []
            b += pos[x:y].tolist()
            a += at[x:y].tolist()
            if alike[x:y].any():
                run = np.stack([pos[x:y], at[x:y], alike[x:y]]).astype(np.int64)[:, alike[x:y] > 0]
                runs.append(run)
                b += (run[0] + run[2] - K).tolist()
                a += (run[1] + run[2] - K).tolist()
        if len(out) > 2000:
            yield _chain_rows(out)
            out = []
    if len(b) > 1:
        settle()
    if out:
        yield _chain_rows(out)


def _complete(batches, keys: int):
    """Batches cut anew, so that rows with equal first `keys` columns (by which they are sorted) lie in one."""
    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        held = batch if held is None else pa.concat_batches([held, batch])
        cut = np.flatnonzero(_new(*(held.column(i).to_numpy() for i in range(keys))))[-1]
        if cut:
            yield held.slice(0, cut)
            held = held.slice(cut)
    if held is not None:
        yield held


def _places(docs):
    """h, doc, t, pos: each text's minimizers, t being the begin of its MD5."""

    def run(batches):
        for part in slices(batches, "t"):
            words = Words(part.column(1))
            gram, at = minimizers(words)
            doc = words.doc[at]
            t = np.array([_named(hashlib.md5(words.data[x:y], usedforsecurity=False).digest()) for x, y in zip(words.offsets, words.offsets[1:], strict=False)], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(gram.view(np.int64)), part.column(0).take(pa.array(doc)), pa.array(t[doc]), pa.array((at - words.first[doc]).astype(np.int32))], names=["h", "doc", "t", "pos"])

    return docs.mapInArrow(run, "h long, doc long, t long, pos int")


def _named(digest: bytes) -> int:
    return int.from_bytes(digest[:8], "big", signed=True)


def _ranked(batches):
    """Rows (h, doc, t, pos) sorted by h, doc: those of seeds of several documents, and how many smaller ones hold the seed (2: or more)."""
    held, last = None, None  # the rows of an open group's only document; or its h, last document and that one's rank
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = batch if held is None else pa.concat_batches([held, batch])
        h, doc = rows.column(0).to_numpy(), rows.column(1).to_numpy()
        run, _, head, _ = _runs(h, doc)
        rank, several = run - head[run], (np.bincount(head, minlength=len(head)) > 1)[head[run]]
        if last and last[0] == h[0]:
            on = head[run] == 0
            rank[on] += last[2] + int(doc[0] != last[1])
            several |= on
        held, last = None, (int(h[-1]), int(doc[-1]), int(rank[-1]))
        if not several[-1]:
            held, last = rows.filter(pa.array(h == h[-1])), None
        if several.any():
            out = rows.filter(pa.array(several))
            yield pa.RecordBatch.from_arrays([out.column(1), out.column(2), out.column(3), pa.array(np.minimum(rank[several], 2).astype(np.int32)), out.column(0)], names=["doc", "t", "pos", "rank", "h"])


ISLANDS = "isl long, doc long, h binary, pos binary, loose binary"


def _islands(batches):
    """Rows (doc, t, pos, rank, h) sorted by all but h; those of rank -1 are the words pos to h that a passage covers.

    Shared seeds of a text that follow each other within MAX_GAP make an island, which no chain leaves. Loose are its
    seeds that no passage covers and a smaller document holds, if one of the island has more than two holders: else
    all its links were made.
    """
    for rows in _complete(batches, 2):
        doc, t, pos, rank, h = (rows.column(i).to_numpy().astype(np.int64) for i in range(5))
        text = np.cumsum(_new(doc, t))
        upto = np.maximum.accumulate((text << 32) + np.where(rank < 0, h, 0))
        seed = (rank >= 0) & _new(doc, t, pos, rank)
        doc, t, pos, rank, h, text, covered = (x[seed] for x in (doc, t, pos, rank, h, text, upto >= (text << 32) + pos + K))
        if not len(h):
            continue
        new = _new(text)
        new[1:] |= pos[1:] - pos[:-1] > MAX_GAP
        island = np.cumsum(new) - 1
        late = np.bincount(island, rank >= 2) > 0
        loose = ~covered & (rank >= 1) & late[island]
        begin = np.flatnonzero(new)
        name = mix(mix(mix(doc[begin].view(np.uint64)) + t[begin].view(np.uint64)) + pos[begin].view(np.uint64)).view(np.int64)
        order = np.lexsort((pos, h, island))
        bounds = np.append(begin, len(h))
        h, pos, loose = h[order], pos[order].astype(np.int32), loose[order]
        several = np.flatnonzero(np.diff(bounds) > 1)
        if len(several):
            packed = [[x[bounds[i] : bounds[i + 1]].tobytes() for i in several] for x in (h, pos, loose)]
            yield pa.RecordBatch.from_arrays([pa.array(name[several]), pa.array(doc[begin][several]), *(pa.array(x, pa.binary()) for x in packed)], names=[x.split()[0] for x in ISLANDS.split(", ")])


#: Loose seeds are named to the workers by so many bits; one taken for another makes pairs for nothing, but loses none.
BITS = 24


#: A seed and the first one beyond the words that two texts have alike around it are at most so far apart.
APART = MAX_GAP + MIN_WORDS
#: Words looked at on each side of a seed.
AROUND = 64
EVIDENCE = "key long, doc long, isl long, lo int, hi int, loose boolean, cls long, words binary"


def _spots(h, pos, loose, island):
    """Seeds sorted by island and pos: their spots (island, h, begin, end, loose), sorted by island and begin; a seed that goes on over itself has one."""
    order = np.lexsort((pos, h, island))
    h, pos, loose, island = h[order], pos[order], loose[order], island[order]
    new = _new(island, h)
    new[1:] |= pos[1:] - pos[:-1] >= K
    begin = np.flatnonzero(new)
    spots = [island[begin], h[begin], pos[begin], pos[np.append(begin[1:], len(h)) - 1], np.logical_or.reduceat(loose, begin)]
    order = np.lexsort((spots[2], spots[0]))
    return [x[order] for x in spots]


def _evidence(bits: bytes):
    """Texts and their islands (doc, t, of): what a passage around a loose seed (in bits) shares with the earlier text (EVIDENCE).

    Two texts are alike in fewer than MIN_WORDS words around a loose seed, or a passage would cover it. A passage goes
    on either by another seed, and then the words from one to the other differ: so each spot has a key with each other one
    within APART, lo to hi being their distances and cls the words. Or it goes on word by word: then the key is the
    spot's seed, and words are those before and after its begin (or its end, if that is another place).
    """

    def run(batches):
        wanted = np.frombuffer(bits, np.uint8)
        for part in slices(batches, "t"):
            words = Words(part.column(1))
            gram, at = words.grams(K)
            up, down = _powers_for(len(words.hash))
            with np.errstate(over="ignore"):
                total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(words.hash) * up[: len(words.hash)])])
            named, seed = [], []
            for i, islands in enumerate(part.column(2).to_pylist()):
                for x in islands:
                    h, pos, loose = (np.frombuffer(x[n], t) for n, t in (("h", np.uint64), ("pos", np.int32), ("loose", np.bool_)))
                    pos = pos + words.first[i]
                    place = np.minimum(np.searchsorted(at, pos), len(at) - 1)
                    if len(at) and pos.max() < words.first[i + 1] and (gram[place] == h).all():  # else those of another text of the id
                        seed.append((h, pos, loose, np.full(len(h), len(named))))
                        named.append((i, x["isl"]))
            if not seed:
                continue
            island, h, begin, end, loose = _spots(*(np.concatenate(x) for x in zip(*seed, strict=True)))
            code = (h & np.uint64((1 << BITS) - 1)).astype(np.int64)
            open_ = (wanted[code >> 3] >> (code & 7)) & 1 == 1
            long = np.flatnonzero(open_ & (end > begin))
            zero = np.zeros(len(long), np.int64)
            found = [np.stack([mix(mix(h[long]) * np.uint64(3) + h[long] * np.uint64(sign)).view(np.int64), island[long], zero, end[long] - begin[long], loose[long], zero]) for sign in (1, 2)]
            step = 1
            while step < len(h):
                x = np.flatnonzero((island[step:] == island[:-step]) & (begin[step:] - end[:-step] <= APART))
                if not len(x):
                    break
                y = x + step
                x, y = x[open_[x] | open_[y]], y[open_[x] | open_[y]]
                last = np.maximum(end[x], end[y]) + K
                with np.errstate(over="ignore"):
                    between = mix((total[last] - total[begin[x]]) * down[begin[x]] + (last - begin[x]).astype(np.uint64)).view(np.int64)
                for u, v, sign in ((x, y, 1), (y, x, 2)):
                    of = open_[u]
                    u, v = u[of], v[of]
                    found.append(np.stack([mix(mix(h[u]) * np.uint64(3) + h[v] * np.uint64(sign)).view(np.int64), island[u], np.maximum(begin[y[of]] - end[x[of]], 0), last[of] - K - begin[x[of]], loose[u], between[of]]))
                step += 1
            found = np.concatenate(found, 1)
            found = found[:, np.lexsort((found[5], found[1], found[0]))]
            first = np.flatnonzero(_new(found[0], found[1], found[5])) if found.shape[1] else zero[:0]
            lo, hi, any_ = (f.reduceat(found[i], first) if len(first) else found[i] for f, i in ((np.minimum, 2), (np.maximum, 3), (np.maximum, 4)))
            rows = [found[0][first], found[1][first], lo, hi, any_, found[5][first]]
            around = [None] * len(first)
            low = (words.hash >> np.uint64(32)).astype(np.uint32)
            for side, places, which in ((0, begin, np.flatnonzero(open_)), (1, end, long)):
                key = mix(h[which] ^ np.uint64(0x5DEECE66D + side)).view(np.int64)
                zero = np.zeros(len(which), np.int64)
                rows = [np.append(x, y) for x, y in zip(rows, (key, island[which], zero, zero, loose[which], zero), strict=True)]
                for p, k in zip(places[which].tolist(), island[which].tolist(), strict=True):
                    a, z = words.first[named[k][0]], words.first[named[k][0] + 1]
                    before, after = low[max(a, p - AROUND) : p], low[p : min(z, p + AROUND)]
                    around.append(np.uint32(len(before)).tobytes() + before.tobytes() + after.tobytes())
            of = pa.array([i for i, _ in named]), pa.array([x for _, x in named], pa.int64())
            to = pa.array(rows[1])
            yield pa.RecordBatch.from_arrays([pa.array(rows[0]), part.column(0).take(of[0].take(to)), of[1].take(to), pa.array(rows[2].astype(np.int32)), pa.array(rows[3].astype(np.int32)), pa.array(rows[4] > 0), pa.array(rows[5]), pa.array(around, pa.binary())], names=[x.split()[0] for x in EVIDENCE.split(", ")])

    return run


def _across(cls, doc, loose):
    """Pairs (x, y) of rows of different cls, x loose and y of a smaller document, in parts."""
    if len(doc) <= 256:
        x = np.flatnonzero(loose)
        u, v = np.nonzero((doc[x, None] > doc) & (cls[x, None] != cls))
        if len(u):
            yield x[u], v
        return
    order = np.argsort(cls, kind="stable")
    bounds = np.append(np.flatnonzero(_new(cls[order])), len(order))
    for a, z in zip(bounds, bounds[1:], strict=False):
        x = order[a:z][loose[order[a:z]]]
        y = np.concatenate([order[:a], order[z:]])
        if len(x) and len(y):
            for part in np.array_split(x, -(-len(x) * len(y) // (1 << 20))):
                u, v = np.nonzero(doc[y] < doc[part, None])
                if len(u):
                    yield part[u], y[v]


def _sides(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The words before (from the last on) and after each place, AROUND of each; what a text lacks equals nothing."""
    own = (mix(np.arange(2 * AROUND * len(words), dtype=np.uint64) + np.uint64(0xC0FFEE)) >> np.uint64(32)).astype(np.uint32).reshape(2, len(words), AROUND)
    for i, x in enumerate(words):
        x = np.frombuffer(x, np.uint32)
        before, after = x[1 : 1 + x[0]][::-1], x[1 + x[0] :]
        own[0, i, : len(before)], own[1, i, : len(after)] = before, after
    return own[0], own[1]


def _most(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """What reach() finds in rows of words; all of a row where it has not ended."""
    score = np.cumsum(np.where(x == y, 1.0, -2.0), 1)
    over = np.maximum.accumulate(np.maximum(score, 0), 1) - score > 6
    ended = np.logical_or.accumulate(over, 1)
    best = np.argmax(np.where(ended, -1e9, score), 1)
    top = np.where(ended, -1e9, score)[np.arange(len(best)), best]
    return np.where(ended[:, -1], np.where(top > 0, best + 1, 0), x.shape[1])


#: reach() passes at most so many words without two equal ones in a row.
PAUSE = 9


def _going_on(doc, loose, words, all_pairs: int = 1 << 14):
    """Places of one seed: pairs (x, y), x loose and y of a smaller document, whose words are alike over MIN_WORDS and more around it.

    Beyond the words all alike come at most PAUSE others, then two equal ones: in large groups pairs that have them, and
    another word before, are looked at.
    """
    sides = _sides(words)
    if int(loose.sum()) * len(doc) <= all_pairs:
        x, y = np.nonzero(loose[:, None] & (doc[:, None] > doc))
        found = [(x, y)]
    else:
        found = []
        for side in sides:
            alike = np.zeros((len(doc), AROUND + 1), np.uint64)
            with np.errstate(over="ignore"):
                for j in range(AROUND):
                    alike[:, j + 1] = mix(alike[:, j] * np.uint64(3) + side[:, j])
                for j in range(1, AROUND - 1):
                    key = mix(alike[:, max(0, j - PAUSE)] + mix(side[:, j] * np.uint64(1 << 32) + side[:, j + 1]))
                    order = np.lexsort((side[:, j - 1], key))
                    bounds = np.append(np.flatnonzero(_new(key[order])), len(order))
                    last = side[order, j - 1]
                    for k in np.flatnonzero((last[bounds[:-1]] != last[bounds[1:] - 1]) & np.logical_or.reduceat(loose[order], bounds[:-1])):
                        rows = order[bounds[k] : bounds[k + 1]]
                        found += [(rows[x], rows[y]) for x, y in _across(side[rows, j - 1], doc[rows], loose[rows])]
        pairs = np.unique(np.concatenate([x * len(doc) + y for x, y in found])) if found else np.zeros(0, np.int64)
        found = [(pairs // len(doc), pairs % len(doc))]
    for x, y in found:
        for i in range(0, len(x), 1 << 14):
            u, v = x[i : i + (1 << 14)], y[i : i + (1 << 14)]
            enough = _most(sides[0][u], sides[0][v]) + _most(sides[1][u], sides[1][v]) >= MIN_WORDS
            yield u[enough], v[enough]


def _partners(batches):
    """EVIDENCE sorted by key, doc: (isl, of), the islands of loose rows with those of smaller documents with which they may have a passage."""
    for rows in _complete(batches, 1):
        key, doc, isl, lo, hi, loose, cls = (rows.column(i).to_numpy(zero_copy_only=False) for i in range(7))
        around = rows.column(7)
        bounds = np.append(np.flatnonzero(_new(key)), len(key))
        given = around.is_valid().to_numpy(zero_copy_only=False)
        some = np.logical_or.reduceat(loose & (doc > np.repeat(doc[bounds[:-1]], np.diff(bounds))), bounds[:-1])
        some &= given[bounds[:-1]] | (np.minimum.reduceat(cls, bounds[:-1]) < np.maximum.reduceat(cls, bounds[:-1]))
        u, v = [], []
        for a, z in zip(bounds[:-1][some], bounds[1:][some], strict=True):
            if given[a]:
                for x, y in _going_on(doc[a:z], loose[a:z], around[int(a) : int(z)].to_pylist()):
                    u.append(isl[a + x])
                    v.append(isl[a + y])
            else:
                for x, y in _across(cls[a:z], doc[a:z], loose[a:z]):
                    x, y = a + x, a + y
                    near = (lo[y] - MAX_SHIFT <= hi[x]) & (hi[y] + MAX_SHIFT >= lo[x])
                    u.append(isl[x[near]])
                    v.append(isl[y[near]])
        if u:
            pairs = np.unique(np.stack([np.concatenate(u), np.concatenate(v)]), axis=1)
            if pairs.shape[1]:
                yield pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], names=["isl", "of"])


def _rechained(batches):
    """Rows (doc, h, pos, loose, src, sh, sp) of two islands: the chains of all their shared seeds that hold a loose one."""
    for batch in (b.slice(i, 2000) for b in batches for i in range(0, b.num_rows, 2000)):
        out = []
        for doc, h, pos, loose, src, sh, sp in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            h, pos, loose, sh, sp = (np.frombuffer(x, t) for x, t in ((h, np.int64), (pos, np.int32), (loose, np.bool_), (sh, np.int64), (sp, np.int32)))
            first, end = np.searchsorted(sh, h), np.searchsorted(sh, h, "right")
            at = np.flatnonzero(end > first)
            if not loose[at].any():
                continue
            k = np.minimum(at - np.searchsorted(h, h[at]), end[at] - first[at] - 1)
            b, a = np.concatenate([pos[at], pos[at]]).tolist(), np.concatenate([sp[first[at]], sp[first[at] + k]]).tolist()
            open_ = set(pos[at][loose[at]].tolist())
            out += [(doc, src, *x) for x in _promising(b, a) if not open_.isdisjoint(x[0])]
        if out:
            yield _chain_rows(out)


WINDOWS = "doc long, lo int, hi int, h binary, s binary, n binary, g binary"


def _windows(batches):
    """Rows (doc, t, w: list of lo, hi): 32-bit word hashes, and each word's code points since the last one's begin and its length, of the windows, and the text's MD5."""
    for part in slices(batches, "t"):
        words = Words(part.column(1))
        whole = np.concatenate([[0], np.cumsum((words.data & 0xC0) != 0x80)])
        h, base = (words.hash >> np.uint64(32)).astype(np.uint32), whole[words.offsets]
        rows = []
        for i, (doc, wanted) in enumerate(zip(part.column(0).to_pylist(), part.column(2).to_pylist(), strict=True)):
            digest = hashlib.md5(words.data[words.offsets[i] : words.offsets[i + 1]], usedforsecurity=False).digest()
            for w in wanted:
                a, z = words.first[i] + w["lo"], min(words.first[i] + w["hi"], words.first[i + 1])
                begin = whole[words.start[a:z]] - base[i]
                rows.append((doc, w["lo"], w["hi"], h[a:z].tobytes(), np.diff(begin, prepend=0).astype(np.int32).tobytes(), (whole[words.end[a:z]] - base[i] - begin).astype(np.int32).tobytes(), digest))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), [pa.int64(), pa.int32(), pa.int32(), *[pa.binary()] * 4], strict=True)], names=[x.split()[0] for x in WINDOWS.split(", ")])


def common_words(x: np.ndarray, y: np.ndarray) -> int:
    """Length of the longest common subsequence of two short word lists."""
    row = np.zeros(len(y) + 1, np.int32)
    for v in x:
        new = row.copy()
        np.maximum(new[1:], row[:-1] + (y == v), out=new[1:])
        row = np.maximum.accumulate(new)
    return int(row[-1])


def reach(x: np.ndarray, y: np.ndarray, miss: float = 2.0, drop: float = 6.0) -> tuple[int, int]:
    """How far two word lists go on alike from their start (the best prefix, ended where the score has dropped), and its equal words."""
    n = min(len(x), len(y))
    if not n:
        return 0, 0
    same = x[:n] == y[:n]
    if same.all():
        return n, n
    score = np.cumsum(np.where(same, 1.0, -miss))
    over = np.flatnonzero(np.maximum.accumulate(np.maximum(score, 0)) - score > drop)
    end = int(over[0]) if len(over) else n
    best = int(np.argmax(score[:end])) + 1 if end else 0
    return (best, int(same[:best].sum())) if best and score[best - 1] > 0 else (0, 0)


def align(b: list[int], a: list[int], x: np.ndarray, y: np.ndarray, k: int = K) -> tuple[int, int, int, int, int]:
    """(begin, end) in x, (begin, end) in y and the equal words of a chain of anchors; x, y: the word hashes around it."""
    equal = 0
    for i in range(len(b) - 1):
        db, da = b[i + 1] - b[i], a[i + 1] - a[i]
        u, v = x[b[i] : b[i + 1]], y[a[i] : a[i + 1]]
        equal += int((u == v).sum()) if db == da else common_words(u, v)
    left, same = reach(x[: b[0]][::-1], y[: a[0]][::-1])
    right, more = reach(x[b[-1] + k :], y[a[-1] + k :])
    return b[0] - left, b[-1] + k + right, a[0] - left, a[-1] + k + right, equal + k + same + more


def alike(b: list[int], a: list[int], x: np.ndarray, y: np.ndarray, k: int = K) -> list[tuple[int, int, int, int, int]]:
    """What align() gives, of the parts of a chain that are alike word by word and have MIN_WORDS."""
    out, first = [], 0
    for i in range(1, len(b) + 1):
        if i == len(b) or b[i] - b[i - 1] != a[i] - a[i - 1] or (x[b[i - 1] : b[i]] != y[a[i - 1] : a[i]]).any():
            if b[i - 1] + k - b[first] >= MIN_WORDS:
                out.append((b[first], b[i - 1] + k, a[first], a[i - 1] + k, b[i - 1] + k - b[first]))
            first = i
    return out


PASSAGES = "doc_id long, start long, end long, source_id long, source_start long, source_end long, n_words int, n_equal int, digest binary"
FOUND = PASSAGES + ", t long, pos int, until int"


def _aligned(batches):
    for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
        c = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
        rows = []
        for doc, src, bs, as_, b_lo, a_lo, hx, sx, nx, hy, sy, ny, digest in zip(*(c[n].to_pylist() for n in ("doc", "src", "bs", "as", "b_lo", "a_lo", "bh", "bb", "bn", "ah", "ab", "an", "bg")), strict=True):
            x, y = np.frombuffer(hx, np.uint32), np.frombuffer(hy, np.uint32)
            if bs[-1] + K - b_lo > len(x) or max(as_) + K - a_lo > len(y):
                continue  # the window of another text of the id
            bs, as_ = [p - b_lo for p in bs], [p - a_lo for p in as_]
            got = align(bs, as_, x, y)
            if got[4] < IDENTITY * max(got[1] - got[0], got[3] - got[2]):
                got = alike(bs, as_, x, y)  # what lies between them, or around, is not to lose them
            else:
                got = [got] if got[1] - got[0] >= MIN_WORDS else []
            for b0, b1, a0, a1, equal in got:
                s, t = (np.cumsum(np.frombuffer(v, np.int32)) for v in (sx, sy))
                n, m = (np.frombuffer(v, np.int32) for v in (nx, ny))
                rows.append((doc, int(s[b0]), int(s[b1 - 1] + n[b1 - 1]), src, int(t[a0]), int(t[a1 - 1] + m[a1 - 1]), b1 - b0, equal, digest, _named(digest), b_lo + b0, b_lo + b1))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64() if i < 6 or i == 9 else pa.binary() if i == 8 else pa.int32()) for i, v in enumerate(zip(*rows, strict=True))], names=[z.split()[0] for z in FOUND.split(", ")])


def _outer(batches):
    """Passages sorted by doc_id, digest, start, -end, source_id: those that lie in no other of their text."""
    doc, upto = None, -1
    for batch in batches:
        keep = []
        for d, end, digest in zip(*(batch.column(i).to_pylist() for i in (0, 2, 8)), strict=True):
            if (d, digest) != doc:
                doc, upto = (d, digest), -1
            keep.append(end > upto)
            upto = max(upto, end)
        yield batch.filter(pa.array(keep, pa.bool_()))


def _verified(texts, chained):
    """Chains: those that are passages (FOUND)."""
    wanted = chained.select("doc", F.col("b_lo").alias("lo"), F.col("b_hi").alias("hi")).union(chained.select("src", "a_lo", "a_hi")).distinct()
    wanted = wanted.groupBy("doc").agg(F.collect_list(F.struct("lo", "hi")).alias("w"))  # as many as the text's own length allows
    windows = written(texts.join(wanted, "doc").select("doc", "t", "w").mapInArrow(_windows, WINDOWS), "windows", free=True)
    side = lambda p, d: windows.select(F.col("doc").alias(d), F.col("lo").alias(f"{p}_lo"), F.col("hi").alias(f"{p}_hi"), F.col("h").alias(f"{p}h"), F.col("s").alias(f"{p}b"), F.col("n").alias(f"{p}n"), F.col("g").alias(f"{p}g"))
    rows = chained.join(side("b", "doc"), ["doc", "b_lo", "b_hi"]).join(side("a", "src"), ["src", "a_lo", "a_hi"])
    rows = rows.select("doc", "src", "bs", "as", "b_lo", "a_lo", "bh", "bb", "bn", "ah", "ab", "an", "bg").mapInArrow(_aligned, FOUND)
    return written(rows, "found", free=True)


def _left_open(texts, found, parts):
    """The chains of what the passages found leave open, with every smaller document."""
    shared = _places(texts).repartition(parts, "h").sortWithinPartitions("h", "doc").mapInArrow(_ranked, "doc long, t long, pos int, rank int, h long")
    covered = found.select(F.col("doc_id").alias("doc"), "t", "pos", F.lit(-1).alias("rank"), F.col("until").cast("long").alias("h"))
    islands = shared.union(covered).repartition(parts, "doc").sortWithinPartitions("doc", "t", "pos", "rank").mapInArrow(_islands, ISLANDS)
    islands = written(islands, "islands", free=True)

    def codes(batches):
        for batch in batches:
            h, loose = (np.frombuffer(b"".join(batch.column(i).to_pylist()), t) for i, t in ((0, np.int64), (1, np.bool_)))
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(h[loose] & ((1 << BITS) - 1)))], names=["code"])

    bits = np.zeros(1 << BITS - 3, np.uint8)
    code = islands.select("h", "loose").mapInArrow(codes, "code long").distinct().toArrow().column(0).to_numpy()
    np.bitwise_or.at(bits, code >> 3, (1 << (code & 7)).astype(np.uint8))

    def named(batches):
        wanted = np.frombuffer(bits, np.uint8)
        for batch in batches:
            code = [np.frombuffer(x, np.int64) & ((1 << BITS) - 1) for x in batch.column(2).to_pylist()]
            yield batch.filter(pa.array([bool(((wanted[c >> 3] >> (c & 7)) & 1).any()) for c in code], pa.bool_()))

    bits = bits.tobytes()
    of = islands.mapInArrow(named, ISLANDS).groupBy("doc").agg(F.collect_list(F.struct("isl", "h", "pos", "loose")).alias("of"))  # as many as the text's own length allows
    evidence = texts.join(of, "doc").select("doc", "t", "of").mapInArrow(_evidence(bits), EVIDENCE)
    pairs = evidence.repartition(parts, "key").sortWithinPartitions("key", "doc").mapInArrow(_partners, "isl long, of long").distinct()
    rows = pairs.join(islands, "isl").join(islands.select(F.col("isl").alias("of"), F.col("doc").alias("src"), F.col("h").alias("sh"), F.col("pos").alias("sp")), "of")
    return written(rows.select("doc", "h", "pos", "loose", "src", "sh", "sp").mapInArrow(_rechained, CHAINS), "rechained", free=True)


def passages(docs, id_col: str = "doc_id", text_col: str = "text"):
    """One row per repeated passage (PASSAGES; code points, end exclusive; source_id is the smaller document)."""
    spark = ready(docs.sparkSession)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    texts = docs.select(docs[id_col].cast("long").alias("doc"), docs[text_col].alias("t")).where("doc IS NOT NULL")
    links = seeds(texts).repartition(parts, "h").sortWithinPartitions("h", "doc", "pos").mapInArrow(_linked, "doc long, src long, pos int, at int, alike int")
    chained = written(links.repartition(parts, "doc").sortWithinPartitions("doc", "src", "pos", "at").mapInArrow(_chained, CHAINS), "chains", free=True)
    found = _verified(texts, chained)
    rows = found.union(_verified(texts, _left_open(texts, found, parts))).drop("t", "pos", "until")
    return rows.repartition(parts, "doc_id").sortWithinPartitions("doc_id", "digest", "start", F.desc("end"), "source_id", "source_start").mapInArrow(_outer, PASSAGES)


def op6_passages(spark, sf_dir):
    return passages(table(spark, sf_dir, "documents")).drop("digest")
