"""SentencePiece encoding by suffix-array matching, and decoding.

The distinct segments of a batch (a run of spaces and the word behind it; no piece reaches further) are laid end to
end, a suffix array of that text is built by prefix doubling, and every piece of the vocabulary is searched in it by
bisection, character by character, which gives all its occurrences as a range. The occurrences are the edges of a
lattice, sorted by position; relaxation then merges, in every segment, the two neighbouring symbols whose joint edge
has the best score (leftmost of equals) until none is left, as the models of merged pieces ask for. Characters without
a piece become their UTF-8 bytes' pieces. The ids are those of the sentencepiece library.

Defined results: null text is an empty one and has no ids; equal texts have equal ids; an empty table gives no rows;
further columns are ignored; segments of any length are encoded (from LONG characters on with a heap).
"""

from __future__ import annotations

import heapq
import re
from itertools import chain

import numpy as np
import pyarrow as pa

from .common import as_text, raw, ready, slices, table

SPACE, LONG = "▁", 200
_SEGMENTS = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+").findall


def suffix_array(text: np.ndarray, depth: int) -> np.ndarray:
    """Positions in the order of the suffixes' first `depth` characters (at least). text: small integers."""
    n = len(text)
    bits = max(1, int(text.max(initial=0)).bit_length())
    step = max(1, 62 // bits)
    key = np.zeros(n, np.int64)
    for k in range(step):
        key <<= bits
        key[: max(0, n - k)] |= text[k:]
    order = np.argsort(key)
    while step < depth:
        new = np.ones(n, np.int64)
        new[1:] = key[order[1:]] != key[order[:-1]]
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(new)
        key = rank * (n + 1)
        key[: max(0, n - step)] += rank[step:]
        order = np.argsort(key)
        step *= 2
    return order


def occurrences(text: np.ndarray, order: np.ndarray, pieces: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Range in the suffix array of each piece (rows of `pieces`, padded) by bisection."""
    n = len(text)
    ended = np.append(text, -1)
    head = np.bincount(text, minlength=int(max(text.max(initial=0), pieces[:, 0].max(initial=0))) + 2)
    upto = np.concatenate([[0], np.cumsum(head)])
    lo, hi = upto[pieces[:, 0]], upto[pieces[:, 0] + 1]
    for d in range(1, pieces.shape[1]):
        at = np.flatnonzero((length > d) & (lo < hi))
        if not len(at):
            break
        want = pieces[at, d]
        for more in (0, 1):
            a, z = lo[at].copy(), hi[at].copy()
            while True:
                open_ = a < z
                if not open_.any():
                    break
                mid = (a + z) >> 1
                go = open_ & (ended[np.minimum(order[np.minimum(mid, n - 1)] + d, n)] < want + more)
                a = np.where(go, mid + 1, a)
                z = np.where(open_ & ~go, mid, z)
            if more:
                hi[at] = a
            else:
                lo[at] = a
    hi[length == 0] = lo[length == 0]
    return lo, hi


class Numbered(dict):
    """Numbers keys as they come; new: those of which nothing else is known yet."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, key):
        self[key] = at = len(self)
        self.new.append(key)
        return at


class PieceCoder:
    """Encoder and decoder of one sentencepiece model file; keeps the segments it has met, up to `most`."""

    def __init__(self, path: str | None = None, most: int = 900_000, room: int = 400_000):
        import sentencepiece

        if path is None:
            import public_tokenizers

            path = public_tokenizers.path("piece_bpe_32k.model")
        model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.most, self.room = most, room
        self._empty()
        ids = range(model.get_piece_size())
        plain = [i for i in ids if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        names = [model.id_to_piece(i) for i in plain]
        if any(SPACE in p[1:] and p.strip(SPACE) for p in names):
            raise ValueError("a piece has a space behind its first character")
        scores = np.array([model.get_score(i) for i in plain])
        self.rank = np.full(len(ids) + 1, np.iinfo(np.int64).max >> 33, np.int64)  # the last: no piece
        self.rank[plain] = np.unique(-scores, return_inverse=True)[1]
        self.ids, self.longest = np.array(plain, np.int32), max(map(len, names))
        self.length = np.array([len(p) for p in names])
        self.chars = np.zeros((len(names), self.longest), np.int64)
        for k, p in enumerate(names):
            self.chars[k, : len(p)] = [ord(c) for c in p]
        self.byte = {int(model.id_to_piece(i)[3:-1], 16): i for i in ids if model.is_byte(i)}
        self.bytes_of = [b"" if model.is_control(i) else bytes([int(model.id_to_piece(i)[3:-1], 16)]) if model.is_byte(i) else model.id_to_piece(i).replace(SPACE, " ").encode() for i in ids]
        self.unknown = model.unk_id()
        self.blob, self.sizes = np.frombuffer(b"".join(self.bytes_of), np.uint8), np.array([len(x) for x in self.bytes_of])
        self.spots = np.cumsum(self.sizes) - self.sizes

    def _table(self, text: np.ndarray) -> np.ndarray:
        """ids[position, length] of the piece that lies there, or -1."""
        alphabet, small = np.unique(text, return_inverse=True)
        at = np.searchsorted(alphabet, self.chars)
        at[at == len(alphabet)] = 0
        inside = np.arange(self.longest)[None, :] < self.length[:, None]
        have = ((alphabet[at] == self.chars) | ~inside).all(1)
        pieces, length, ids = np.where(inside, at, 0)[have], self.length[have], self.ids[have]
        order = suffix_array(small, self.longest)
        lo, hi = occurrences(small, order, pieces, length)
        count = hi - lo
        spot = order[np.repeat(lo - np.cumsum(count) + count, count) + np.arange(count.sum())]
        size, name = np.repeat(length, count), np.repeat(ids, count)
        edges = np.argsort(spot * 64 + size)  # by position, then length
        out = np.full((len(text) + 1, self.longest + 1), -1, np.int32)
        out[spot[edges], size[edges]] = name[edges]
        return out

    def _relax(self, edge: np.ndarray, start: np.ndarray, seg: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(segment, begin, length) of the final symbols; start, seg: each character's place and segment."""
        size = np.ones(len(start), np.int64)
        none, done = self.rank[-1], []
        while len(start):
            joint = np.full(len(start), none, np.int64)
            pair = np.flatnonzero(seg[1:] == seg[:-1])
            both = size[pair] + size[pair + 1]
            fits = both <= self.longest
            pair, both = pair[fits], both[fits]
            joint[pair] = self.rank[edge[start[pair], both]]  # -1 is the last: none
            first = np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1]]))
            best = np.minimum.reduceat((joint << 32) | np.arange(len(start)), first)
            at, open_ = best & 0xFFFFFFFF, (best >> 32) < none
            of = np.repeat(np.arange(len(first)), np.diff(first, append=len(start)))
            stop = ~open_[of]
            if stop.any():
                done.append((seg[stop], start[stop], size[stop]))
            at = at[open_]
            size[at] += size[at + 1]
            keep = ~stop
            keep[at + 1] = False
            start, seg, size = start[keep], seg[keep], size[keep]
        out = [np.concatenate(x) for x in zip(*done, strict=True)] if done else [np.zeros(0, np.int64)] * 3
        order = np.lexsort((out[1], out[0]))
        return out[0][order], out[1][order], out[2][order]

    def _merge_long(self, edge: np.ndarray, begin: int, n: int) -> list[tuple[int, int]]:
        """(begin, length) of one long segment's symbols, by a heap of candidate merges."""
        size, nxt, prv = [1] * n, list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, int, int]] = []

        def offer(i):
            if 0 <= i and nxt[i] < n and (both := size[i] + size[nxt[i]]) <= self.longest and (e := edge[begin + i, both]) >= 0:
                heapq.heappush(heap, (int(self.rank[e]), i, size[i], size[nxt[i]]))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = nxt[i] if size[i] == a else n
            if not a or j >= n or size[j] != b:
                continue
            size[i], size[j] = a + b, 0
            nxt[i] = nxt[j]
            if nxt[i] < n:
                prv[nxt[i]] = i
            offer(prv[i])
            offer(i)
        return [(begin + i, size[i]) for i in range(n) if size[i]]

    def _empty(self):
        """index: a segment without its first space -> its number; its ids: store[begin : begin + count]."""
        self.index, self.begin, self.count, self.store, self.held = Numbered(), np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64), np.zeros(1 << 18, np.int32), 0

    def _keep(self, first: int, ids: np.ndarray, count: np.ndarray):
        """The ids of the segments numbered from `first`."""
        while first + len(count) > len(self.begin):
            self.begin, self.count = np.resize(self.begin, 2 * len(self.begin)), np.resize(self.count, 2 * len(self.count))
        while self.held + len(ids) > len(self.store):
            self.store = np.resize(self.store, 2 * len(self.store))
        self.store[self.held : self.held + len(ids)] = ids
        self.begin[first : first + len(count)] = self.held + np.cumsum(count) - count
        self.count[first : first + len(count)] = count
        self.held += len(ids)

    def _learn(self):
        new = [SPACE + s for s in self.index.new]
        base = len(self.index) - len(new)
        self.index.new.clear()
        for a, z in self._groups(new):
            group = new[a:z]
            joined = "\0".join(group) + "\0"
            text = np.frombuffer(joined.encode("utf-32-le"), np.uint32).astype(np.int64)
            length = np.array([len(s) for s in group])
            begin = np.cumsum(length + 1) - length - 1
            edge = self._table(text)
            few = np.flatnonzero(length <= LONG)
            seg = np.repeat(few, length[few])
            start = np.repeat(begin[few] - np.cumsum(length[few]) + length[few], length[few]) + np.arange(length[few].sum())
            found = [self._relax(edge, start, seg)]
            for k in np.flatnonzero(length > LONG).tolist():
                parts = self._merge_long(edge, int(begin[k]), int(length[k]))
                found.append((np.full(len(parts), k), *(np.array(x) for x in zip(*parts, strict=True))))
            s, b, n = (np.concatenate(x) for x in zip(*found, strict=True))
            order = np.lexsort((b, s)) if len(found) > 1 else slice(None)
            s, ids, at = s[order], edge[b, n][order], b[order]
            if (ids < 0).any():
                more = {k: [self.byte.get(c, self.unknown) for c in joined[at[k]].encode()] if self.byte else [self.unknown] for k in np.flatnonzero(ids < 0).tolist()}
                wide = np.ones(len(ids), np.int64)
                wide[list(more)] = [len(x) for x in more.values()]
                to = np.cumsum(wide) - wide
                s, ids = np.repeat(s, wide), np.repeat(ids, wide)
                for k, x in more.items():
                    ids[to[k] : to[k] + len(x)] = x
            self._keep(base + a, ids, np.bincount(s, minlength=len(group)))

    def _groups(self, segments):
        a, size = 0, 0
        for z, s in enumerate(segments):
            if size and size + len(s) > self.room:
                yield a, z
                a, size = z, 0
            size += len(s) + 1
        if segments:
            yield a, len(segments)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and each text's number of them."""
        if len(self.index) > self.most:
            self._empty()
        parts = []
        for t in texts:
            if "  " in t or SPACE in t or t[-1:] == " ":
                parts.append([x[1:] for x in _SEGMENTS(SPACE + t.replace(" ", SPACE))])
            elif t[:1] == " ":
                parts.append([SPACE + (x := t[1:].split(" "))[0], *x[1:]])
            else:
                parts.append(t.split(" ") if t else [])
        flat = list(chain.from_iterable(parts))
        at = np.fromiter(map(self.index.__getitem__, flat), np.int64, len(flat))
        if self.index.new:
            self._learn()
        count = self.count[at]
        to = np.cumsum(count)
        ids = self.store[np.repeat(self.begin[at] - to + count, count) + np.arange(to[-1] if len(to) else 0)]
        upto = np.concatenate([[0], to])[np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)]
        return ids, np.diff(upto)

    def bytes_for(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of all ids, and each one's number of them."""
        size = self.sizes[ids]
        to = np.cumsum(size)
        return self.blob[np.repeat(self.spots[ids] - to + size, size) + np.arange(to[-1] if len(to) else 0)], size

    def decode(self, ids) -> str:
        of = self.bytes_of
        return b"".join([of[i] for i in ids]).decode("utf-8", "replace").removeprefix(" ")


_coder: dict[str | None, PieceCoder] = {}


def coder(path: str | None = None) -> PieceCoder:
    if path not in _coder:
        _coder[path] = PieceCoder(path)
    return _coder[path]


ENCODED = "doc_id long, n_tokens int, ids array<int>, round_trip boolean"


def encode(docs, id_col: str = "doc_id", text_col: str = "text", model: str | None = None):
    """One row per document: its ids, how many, and whether decoding them gives the text again."""

    def run(batches):
        code = coder(model)
        for part in slices(batches, "t", 8 << 20):
            ids, count = code.encode(as_text(part.column(1)).to_pylist())
            first = np.concatenate([[0], np.cumsum(count)])
            made, size = code.bytes_for(ids)
            data, off = raw(part.column(1))
            own = np.concatenate([[0], np.cumsum(size)])[first]
            same = [a == z if x == y else made[x + 1 : y].tobytes() == data[a:z].tobytes() for x, y, a, z in zip(own[:-1].tolist(), own[1:].tolist(), off[:-1].tolist(), off[1:].tolist(), strict=True)]
            lists = pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(ids))
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(count.astype(np.int32)), lists, pa.array(same)], names=["doc_id", "n_tokens", "ids", "round_trip"])

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, ENCODED)


def decode(encoded, id_col: str = "doc_id", ids_col: str = "ids", model: str | None = None):
    """doc_id, text of lists of ids (null: empty)."""

    def run(batches):
        code = coder(model)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([code.decode(x or ()) for x in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    ready(encoded.sparkSession)
    return encoded.select(encoded[id_col].cast("long").alias("i"), encoded[ids_col].alias("x")).mapInArrow(run, "doc_id long, text string")


def op2_pieces(spark, sf_dir):
    return encode(table(spark, sf_dir, "documents"))
