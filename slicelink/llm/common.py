"""Shared plumbing: shared folder, lineage cuts, and hashed words straight from Arrow buffers."""

from __future__ import annotations

import os
import tempfile
import uuid
from functools import lru_cache

import numpy as np
import pyarrow as pa

REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
_OWN: dict[str, str] = {}


def ready(spark):
    """Let Python workers import this package also where PYTHONPATH doesn't name it (local runs, tests)."""
    env = spark.sparkContext.environment
    if REPO not in env.get("PYTHONPATH", "").split(":"):
        env["PYTHONPATH"] = ":".join(x for x in (REPO, env.get("PYTHONPATH", "")) if x)
    return spark


def shared_dir(spark) -> str:
    """The folder of spark.checkpoint.dir; where it is unset (tests, one machine) a temporary one."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="slicelink-")
    return _OWN[app]


def fresh_path(spark, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


FREES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def written(df, name: str, free: bool = False):
    """Cut the lineage: write as Parquet into the shared folder and read back; with `free`, delete the shuffle files at once."""
    return written_at(df, name, free)[0]


def written_at(df, name: str, free: bool = False):
    """written(), and the path."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    before = spark.conf.get(FREES, None)
    if free:
        spark.conf.set(FREES, "true")
    try:
        df.write.parquet(path)
    finally:
        if free:
            spark.conf.unset(FREES) if before is None else spark.conf.set(FREES, before)
    return spark.read.schema(df.schema).parquet(path), path


def table(spark, sf_dir: str, name: str):
    return ready(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def as_text(column: pa.Array) -> pa.Array:
    """A string array with 32-bit offsets and without nulls (null: empty)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_string(column.type):
        column = column.cast(pa.string())
    return column.fill_null("") if column.null_count else column


def trim() -> None:
    """Give freed memory back: workers stay alive between tasks, beside others of their executor."""
    import ctypes
    import ctypes.util

    try:
        ctypes.CDLL(ctypes.util.find_library("c")).malloc_trim(0)
    except (AttributeError, OSError, TypeError):  # another C library
        pass


def slices(batches, column: str, most: int = 1 << 20):
    """Record batches cut so that `column` holds about `most` bytes each; one longer text makes one slice."""
    for batch in batches:
        if not batch.num_rows:
            continue
        text = as_text(batch.column(batch.schema.get_field_index(column)))
        offsets = np.frombuffer(text.buffers()[1], np.int32)[text.offset : text.offset + len(text) + 1]
        at = 0
        while at < len(text):
            to = int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1
            to = min(max(to, at + 1), len(text))
            yield batch.slice(at, to - at)
            at = to
    _powers.cache_clear()
    trim()


def raw(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets (len + 1) of a string array, without a copy."""
    text = as_text(text)
    offsets = np.frombuffer(text.buffers()[1], np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
    data = text.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer (in new memory)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


@lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    with np.errstate(over="ignore"):
        up = np.full(n, _BASE, _U)
        down = np.full(n, _INVERSE, _U)
        up[0] = down[0] = 1
        return np.multiply.accumulate(up), np.multiply.accumulate(down)


def _powers_for(n: int):
    return _powers(1 << max(16, (n + 1).bit_length()))


_SCRAMBLE = mix(np.arange(1, 257, dtype=_U) * _U(0xD1342543DE82EF95))
#: The six separators of the word pattern [^\x20\x09-\x0D]+.
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


class Words:
    """Words `[^\\x20\\x09-\\x0D]+` of many texts at once.

    data, offsets: bytes and text offsets; start, end: byte span of each word; doc: its text's index;
    first: index of each text's first word (len + 1); hash: 64-bit hash of each word.
    """

    def __init__(self, text: pa.Array):
        self.data, self.offsets = raw(text)
        n = len(self.data)
        gap = np.ones(n + 2, bool)
        gap[1:-1] = SEPARATOR[self.data]
        inside = ~gap
        # a text's first byte starts a word even if the text before ended inside one
        starts = inside[1:-1] & gap[:-2]
        cut = self.offsets[:-1][self.offsets[:-1] < n]
        starts[cut] |= inside[1:-1][cut]
        ends = inside[1:-1] & gap[2:]
        last = self.offsets[1:][self.offsets[1:] > 0] - 1
        ends[last] |= inside[1:-1][last]
        self.start, self.end = np.flatnonzero(starts), np.flatnonzero(ends) + 1
        self.first = np.searchsorted(self.start, self.offsets)
        self.doc = np.repeat(np.arange(len(self.offsets) - 1), np.diff(self.first))
        self._sums()
        self.hash = self.span_hash(self.start, self.end)

    def _sums(self):
        with np.errstate(over="ignore"):
            self.total = np.zeros(len(self.data) + 1, _U)
            np.cumsum(_SCRAMBLE[self.data] * _powers_for(len(self.data))[0][: len(self.data)], out=self.total[1:])

    def span_hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of the bytes of each span; equal bytes, equal hash, wherever they lie."""
        with np.errstate(over="ignore"):
            x = (self.total[end] - self.total[start]) * _powers_for(len(self.data))[1][start]
            return mix(x + (end - start).astype(_U) * _U(0xA24BAED4963EE407))

    def grams(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of each k words that follow each other, and the index of the first of them; none crosses a text's end."""
        n = len(self.hash)
        if n < k:
            return np.zeros(0, _U), np.zeros(0, np.int64)
        with np.errstate(over="ignore"):
            x = np.zeros(n - k + 1, _U)
            for j in range(k):
                x = x * _U(0x9FB21C651E98DF25) + self.hash[j : n - k + 1 + j]
            at = np.flatnonzero(self.doc[: n - k + 1] == self.doc[k - 1 :])
            return mix(x[at]), at
