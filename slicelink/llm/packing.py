"""Harmonic packing of tokenized documents into sequences of a fixed capacity.

A piece of r tokens is of class k where capacity/(k+1) < r <= capacity/k, and a sequence of class k takes exactly
k pieces. Documents may be cut, so a remainder that would leave more than `slack` of its slot empty gives up a head
of exactly capacity/(k+1) tokens first. Every worker fills its own sequences while it reads; only the open ones
(at most one for each class, some ninety) are held, and what is left in them at the end of the partition is
laid end to end. So nothing is shuffled and memory doesn't grow with the input.

Defined results: null text is an empty one, an empty text is the single end id, equal texts are packed each for
itself, an empty table gives no rows, further columns are ignored.
"""

from __future__ import annotations

import os
import zlib
from itertools import chain

import numpy as np
import pyarrow as pa

from .common import as_text, ready, slices, table

CAPACITY, END_ID, SLACK = 2048, 1, 1 / 32
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, class int"
_ARROW = pa.schema([(x.split()[0], pa.int64() if x.split()[1] == "long" else pa.int32()) for x in SCHEMA.split(", ")])


def cuts(n: int, capacity: int = CAPACITY, slack: float = SLACK) -> list[tuple[int, int]]:
    """(length, class) of the pieces of a document of n tokens, in order."""
    out = [(capacity, 1)] * (n // capacity)
    r = n % capacity
    while r:
        k = capacity // r
        slot = capacity // k
        if slot - r <= slot * slack:
            out.append((r, k))
            break
        head = capacity // (k + 1)
        out.append((head, k + 1))
        r -= head
    return out


class _Index(dict):
    """Numbers keys as they come; new: those not yet encoded."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, key):
        self[key] = at = len(self)
        self.new.append(key)
        return at


class WordCoder:
    """Ids of tokenizers' word-level BPE file, the same as its encode(), in bulk.

    The merges are given to tiktoken as ranks, an end of word being the byte 0 (tests compare the two); a text with
    control characters or special tokens goes to tokenizers itself. What lies between white space is encoded once
    while it stays in the cache, which is emptied at `most` entries.
    """

    def __init__(self, path: str | None = None, most: int = 700_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        import tiktoken
        from tokenizers import Tokenizer

        if path is None:
            import public_tokenizers

            path = public_tokenizers.path("word_bpe_49k.json")
        self.model, self.most = Tokenizer.from_file(path), most
        # fixed value: the split pattern of the tokenizer file
        self.find = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall
        printed = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in set(printed)]
        byte = {chr(b): b for b in printed} | {chr(256 + i): b for i, b in enumerate(hidden)}
        ends = {t: i for t, i in self.model.get_vocab(with_added_tokens=False).items() if not t.startswith("<|")}
        ranks = {bytes(byte[c] for c in t.removesuffix("</w>")) + b"\0" * t.endswith("</w>"): i for t, i in ends.items()}
        self.ends = np.zeros(max(ranks.values()) + 1, bool)
        self.ends[[i for t, i in ends.items() if t.endswith("</w>")]] = True
        self.ranked = tiktoken.Encoding("words", pat_str=r"[^\x00]*\x00", mergeable_ranks=ranks, special_tokens={})
        self._empty()

    def _empty(self):
        self.index, self.begin, self.count, self.ids, self.n = _Index(), np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64), np.zeros(1 << 18, "<u4"), 0

    def _learn(self):
        words = [self.find(x) for x in self.index.new]
        ids = np.array(self.ranked.encode_ordinary("\0".join(chain.from_iterable(words)) + "\0"), "<u4")
        to = np.flatnonzero(self.ends[ids]) + 1
        upto = np.concatenate([[0], to])[np.cumsum([len(w) for w in words])]
        first, last = len(self.index) - len(words), len(self.index)
        while last > len(self.begin):
            self.begin, self.count = np.resize(self.begin, 2 * len(self.begin)), np.resize(self.count, 2 * len(self.count))
        while self.n + len(ids) > len(self.ids):
            self.ids = np.resize(self.ids, 2 * len(self.ids))
        self.ids[self.n : self.n + len(ids)] = ids
        self.begin[first:last] = self.n + np.concatenate([[0], upto[:-1]])
        self.count[first:last] = np.diff(upto, prepend=0)
        self.n += len(ids)
        self.index.new.clear()

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        import unicodedata

        if len(self.index) > self.most:
            self._empty()
        parts, odd = [], []
        for i, t in enumerate(texts):
            if "<|" in t or not t.isprintable() and not t.replace("\n", "").replace("\t", "").isprintable():
                odd.append(i)
                parts.append(())
                continue
            if not t.isascii():
                t = unicodedata.normalize("NFC", t).replace("Σ", "σ")  # their lower case knows no final sigma
            parts.append(t.lower().split())
        flat = list(chain.from_iterable(parts))
        at = np.fromiter(map(self.index.__getitem__, flat), np.int64, len(flat))
        if self.index.new:
            self._learn()
        count = self.count[at]
        to = np.cumsum(count)
        ids = self.ids[np.repeat(self.begin[at] - to + count, count) + np.arange(to[-1] if len(to) else 0)]
        upto = 4 * np.concatenate([[0], to])[np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)]
        ids = ids.tobytes()
        out = [ids[a:b] for a, b in zip(upto[:-1].tolist(), upto[1:].tolist(), strict=True)]
        for i in odd:
            out[i] = np.array(self.model.encode(texts[i], add_special_tokens=False).ids, "<u4").tobytes()
        return out


_coder: dict[str | None, WordCoder] = {}


def coder(path: str | None = None) -> WordCoder:
    if path not in _coder:
        _coder[path] = WordCoder(path)
    return _coder[path]


class Bins:
    """The open sequences of one worker."""

    def __init__(self, worker: int, capacity: int = CAPACITY):
        self.next, self.capacity, self.open, self.rows = worker << 36, capacity, {}, []

    def _close(self, pieces: list, kind: int):
        at = 0
        for doc, start, ids, total in pieces:
            n = len(ids) // 4
            self.rows.append((doc, start, n, zlib.crc32(ids), total, self.next, at, kind))
            at += n
        self.next += 1

    def add(self, doc, ids: bytes, slack: float = SLACK):
        total, at = len(ids) // 4, 0
        for n, k in cuts(total, self.capacity, slack):
            piece = (doc, at, ids[4 * at : 4 * (at + n)], total)
            at += n
            if k == 1:
                self._close([piece], 1)
                continue
            held = self.open.setdefault(k, [])
            held.append(piece)
            if len(held) == k:
                self._close(self.open.pop(k), k)

    def finish(self):
        """Lay what is left end to end; its last sequence alone is padded."""
        now, room = [], self.capacity
        for k in sorted(self.open):
            for doc, start, ids, total in self.open[k]:
                while ids:
                    part = ids[: 4 * room]
                    now.append((doc, start, part, total))
                    start, ids, room = start + len(part) // 4, ids[len(part) :], room - len(part) // 4
                    if not room:
                        self._close(now, 0)
                        now, room = [], self.capacity
        if now:
            self._close(now, 0)
        self.open = {}

    def drain(self):
        rows, self.rows = self.rows, []
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), _ARROW.types, strict=True)] if rows else [pa.array([], t) for t in _ARROW.types], schema=_ARROW)


def pack(docs, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, capacity: int = CAPACITY, slack: float = SLACK):
    """One row per piece (SCHEMA; class 0: laid end to end from what was left)."""

    def run(batches):
        from pyspark import TaskContext

        bins, code, end = Bins(TaskContext.get().partitionId(), capacity), coder(tokenizer), np.array([END_ID], "<u4").tobytes()
        for part in slices(batches, "t"):
            for doc, ids in zip(part.column(0).to_pylist(), code.encode(as_text(part.column(1)).to_pylist()), strict=True):
                bins.add(doc, ids + end, slack)
            yield bins.drain()
        bins.finish()
        yield bins.drain()

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, SCHEMA)


def op4_packing(spark, sf_dir):
    return pack(table(spark, sf_dir, "documents"))
