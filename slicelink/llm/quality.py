"""Quality rules: base counts of each text, and perplexity bands of a modified Kneser-Ney model.

The model's units are the bytes of UTF-8, `ORDER` at a time, for each language: all languages share one alphabet, the
table of n-grams grows with the corpus but saturates, and a key packs its n-gram without collisions. Tasks count their
own n-grams in sorted arrays and Spark sums the counts into a table of the shared folder. While that has at most
`most` n-grams, every worker reads it once and turns it into the model (continuation counts, three discounts an order,
interpolation; sorted arrays of keys); beyond that the model is made in SQL and joined to the texts' n-gram counts by
shuffle, with the same result. Nothing of it passes through the driver. A text's perplexity is held against its
language's band, set from the quartiles of all texts (exact, of bits a byte in steps of 1 / `STEPS`) and wider the
shorter the text, whose value is the noisier.

Defined results: every row gives one row, whatever its id (null and repeated ones too); null text has no words, null
language is the empty one; an empty text has no perplexity and fails the base rule; a language whose quartiles coincide
has a band of at least `LEAST_WIDTH` bits to each side; a text on a band's edge is inside; equal texts of one language,
equal verdicts, however the rows are dealt; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from .common import Words, as_text, mix, raw, ready, slices, table, written, written_at

ORDER = 5
#: A text is out where its bits a byte lie further from the median than so many times the quartile's distance, widened
#: by sqrt(1 + LENGTH / bytes). Set so that each side takes about 0.5 % of the documents of sf0.01 that have neither
#: more symbols than a fiftieth of their characters nor label quality 0.
BELOW, ABOVE, LEAST_WIDTH, LENGTH = 4.0, 3.0, 0.05, 1000.0
MOST_ENTRIES, STEPS, MOST_LANGUAGES = 4_000_000, 1000, 10_000
SYMBOLS = np.zeros(256, np.int64)
SYMBOLS[list(b"#*$%&|<>")] = 1
BASE = "doc_id long, lang string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_bytes long"


def keys_of(data: np.ndarray, offsets: np.ndarray, which: np.ndarray, order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """Packed n-grams of the texts `which`, one per byte (zeros before a text), and the number for each text."""
    begin, size = offsets[which], offsets[which + 1] - offsets[which]
    pad = order - 1
    total = int(size.sum())
    at = np.repeat(begin - np.cumsum(size) + size, size) + np.arange(total)
    to = np.arange(total) + pad * np.repeat(np.arange(1, len(which) + 1), size)
    x = np.zeros(total + pad * len(which), np.int64)
    x[to] = data[at]
    out = x.copy()
    for k in range(1, order):
        out[k:] |= x[:-k] << (8 * k)
    return out[to], size


def merged(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    key, n = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(key, kind="stable")
    key, n = key[order], n[order]
    at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    return key[at], np.add.reduceat(n, at) if len(at) else n


def counted(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keys = np.sort(keys)
    at = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[at], np.diff(at, append=len(keys))


def _languages(column) -> dict[str, np.ndarray]:
    names = np.array(as_text(column).to_pylist(), object)
    return {x: np.flatnonzero(names == x) for x in set(names.tolist())}


def ngram_counts(docs, text_col: str = "text", lang_col: str = "lang", order: int = ORDER):
    """lang, key, c: how often each n-gram of the highest order occurs in all texts."""

    def run(batches):
        held: dict[str, tuple[list, list]] = {}
        size = 0

        def out():
            for lang, (keys, counts) in held.items():
                key, n = merged(keys, counts)
                for a in range(0, len(key), 1 << 18):
                    part = key[a : a + (1 << 18)]
                    yield pa.RecordBatch.from_arrays([pa.array([lang]).take(pa.array(np.zeros(len(part), np.int32))), pa.array(part), pa.array(n[a : a + (1 << 18)])], names=["lang", "key", "c"])
            held.clear()

        for part in slices(batches, "t"):
            data, off = raw(part.column(1))
            for lang, which in _languages(part.column(0)).items():
                key, n = counted(keys_of(data, off, which, order)[0])
                keys, counts = held.setdefault(lang, ([], []))
                keys.append(key)
                counts.append(n)
                size += len(key)
            if size > 2_000_000:
                for lang, (keys, counts) in list(held.items()):
                    key, n = merged(keys, counts)
                    held[lang] = ([key], [n])
                size = sum(len(k[0]) for k, _ in held.values())
                if size > 1_500_000:
                    yield from out()
                    size = 0
        yield from out()

    ready(docs.sparkSession)
    rows = docs.select(F.coalesce(docs[lang_col].cast("string"), F.lit("")).alias("l"), docs[text_col].alias("t")).mapInArrow(run, "lang string, key long, c long")
    return rows.groupBy("lang", "key").agg(F.sum("c").alias("c"))


def kneser_ney(counts, order: int = ORDER):
    """lang, n, key, logp, logbow of every n-gram of order n (bow: the weight its suffix-extensions' unseen mass has,
    as a context of order n+1; null where it is none). counts: ngram_counts(), written."""
    mask = lambda k: (1 << 8 * k) - 1
    tables = {order: counts}
    for k in range(order - 1, 0, -1):
        tables[k] = tables[k + 1].groupBy("lang", F.col("key").bitwiseAND(F.lit(mask(k))).alias("key")).agg(F.count("*").alias("c"))
    probs, bows = {}, {}
    for k in range(1, order + 1):
        t = tables[k]
        seen = t.where("c <= 4").groupBy("lang").agg(*(F.sum(F.when(F.col("c") == j, 1).otherwise(0)).cast("double").alias(f"n{j}") for j in (1, 2, 3, 4)))
        y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))
        ratio = lambda j: F.when(F.col(f"n{j}") > 0, F.col(f"n{j + 1}") / F.col(f"n{j}")).otherwise(F.lit(0.0))
        # a discount that counts of counts don't support (too few n-grams) is one half
        own = lambda j: F.coalesce(F.when((F.col("n1") > 0) & (F.col("n2") > 0), F.least(F.greatest(j - (j + 1) * y * ratio(j), F.lit(0.05)), F.lit(j - 0.05))), F.lit(0.5))  # noqa: E731,B023
        disc = seen.select("lang", *(own(j).alias(f"d{j}") for j in (1, 2, 3)))
        t = t.join(F.broadcast(disc), "lang", "left")  # a row for each language
        d = F.when(F.col("c") == 1, F.coalesce("d1", F.lit(0.5))).when(F.col("c") == 2, F.coalesce("d2", F.lit(0.5))).otherwise(F.coalesce("d3", F.lit(0.5)))
        t = t.select("lang", "key", F.shiftright("key", 8).alias("ctx"), F.col("c").cast("double").alias("c"), d.alias("d"))
        w = Window.partitionBy("lang", "ctx")  # at most 256 rows
        t = t.select("lang", "key", "ctx", "c", "d", F.sum("c").over(w).alias("s"), F.sum("d").over(w).alias("ds"))
        if k == 1:
            t = t.withColumn("low", F.lit(1 / 256))
        else:
            low = probs[k - 1].select("lang", F.col("key").alias("suffix"), F.col("p").alias("low"))
            t = t.withColumn("suffix", F.col("key").bitwiseAND(F.lit(mask(k - 1)))).join(low, ["lang", "suffix"])
        bows[k - 1] = t.groupBy("lang", F.col("ctx").alias("key")).agg(F.first(F.log(F.col("ds") / F.col("s"))).alias("logbow"))
        probs[k] = written(t.select("lang", "key", ((F.col("c") - F.col("d") + F.col("ds") * F.col("low")) / F.col("s")).alias("p")), f"kn{k}")
    out = None
    for k in range(0, order + 1):
        p = probs[k].select("lang", F.lit(k).alias("n"), "key", F.log("p").cast("float").alias("logp")) if k else None
        b = bows[k].select("lang", F.lit(k).alias("n"), "key", F.col("logbow").cast("float").alias("logbow")) if k < order else None
        one = p.join(b, ["lang", "n", "key"], "full") if k and k < order else p.withColumn("logbow", F.lit(None).cast("float")) if k else b.withColumn("logp", F.lit(None).cast("float"))
        one = one.select("lang", "n", "key", "logp", "logbow")
        out = one if out is None else out.unionByName(one)
    return out


class Model:
    """Per language and order: sorted keys, log-probabilities, and back-off weights (nan: none)."""

    def __init__(self, of: dict, order: int = ORDER):
        self.of, self.order = of, order

    @classmethod
    def from_counts(cls, counts: pa.Table, order: int = ORDER) -> Model:
        """The same model as kneser_ney() gives, from lang, key, c in memory."""
        lang = counts.column("lang").combine_chunks().dictionary_encode()
        code = lang.indices.to_numpy(zero_copy_only=False)
        key, c = counts.column("key").to_numpy(), counts.column("c").to_numpy()
        of = {}
        for i, name in enumerate(lang.dictionary.to_pylist()):
            at = np.flatnonzero(code == i)
            at = at[np.argsort(key[at])]
            keys, freq = {order: key[at]}, {order: c[at]}
            for k in range(order - 1, 0, -1):
                keys[k], freq[k] = np.unique(keys[k + 1] & ((1 << 8 * k) - 1), return_counts=True)
            low, weights = None, {}
            for k in range(1, order + 1):
                n = [int((freq[k] == j).sum()) for j in range(1, 5)]
                y = n[0] / (n[0] + 2 * n[1]) if n[0] else 0.0
                d = np.array([min(max(j - (j + 1) * y * (n[j] / n[j - 1] if n[j - 1] else 0.0), 0.05), j - 0.05) if n[0] and n[1] else 0.5 for j in (1, 2, 3)])
                d = d[np.minimum(freq[k], 3) - 1]
                ctx = keys[k] >> 8
                first = np.flatnonzero(np.concatenate([[True], ctx[1:] != ctx[:-1]]))
                size = np.diff(first, append=len(ctx))
                s, ds = np.add.reduceat(freq[k].astype(np.float64), first), np.add.reduceat(d, first)
                base = 1 / 256 if low is None else low[np.searchsorted(keys[k - 1], keys[k] & ((1 << 8 * (k - 1)) - 1))]
                low = (freq[k] - d + np.repeat(ds, size) * base) / np.repeat(s, size)
                weights[k - 1] = (ctx[first], np.log(ds / s))
                of[name, k] = [keys[k], np.log(low).astype(np.float32), None]
            of[name, 0] = [np.zeros(1, np.int64), np.full(1, np.nan, np.float32), weights[0][1].astype(np.float32)]
            for k, (ctx, bow) in weights.items():
                if k:
                    at = np.searchsorted(of[name, k][0], ctx)  # contexts at a text's start are no n-grams themselves
                    at[at == len(of[name, k][0])] = 0
                    fits = of[name, k][0][at] == ctx
                    own = np.full(len(of[name, k][0]), np.nan, np.float32)
                    own[at[fits]] = bow[fits]
                    of[name, k][2] = own
            of[name, order][2] = np.full(len(of[name, order][0]), np.nan, np.float32)
        return cls({k: tuple(v) for k, v in of.items()}, order)

    def logp(self, lang: str, keys: np.ndarray) -> np.ndarray:
        """Natural log-probability of the last byte of each key, backing off where an n-gram is unseen."""
        out, open_, n = np.zeros(len(keys)), np.arange(len(keys)), self.order
        while len(open_) and n:
            own = keys[open_] & ((1 << 8 * n) - 1)
            have, logp, _ = self.of.get((lang, n), (np.zeros(0, np.int64),) * 3)
            at = np.searchsorted(have, own)
            at[at == len(have)] = 0
            hit = (have[at] == own) & ~np.isnan(logp[at]) if len(have) else np.zeros(len(own), bool)
            out[open_[hit]] += logp[at[hit]]
            open_, own, n = open_[~hit], own[~hit], n - 1
            ctx = own >> 8
            have, _, bow = self.of.get((lang, n), (np.zeros(0, np.int64),) * 3)
            if len(have) and len(open_):
                at = np.searchsorted(have, ctx)
                at[at == len(have)] = 0
                out[open_] += np.where((have[at] == ctx) & ~np.isnan(bow[at]), bow[at], 0)
        out[open_] += np.log(1 / 256)
        return out


@lru_cache(maxsize=1)
def model_at(path: str) -> Model:
    """The model of a written table of counts, once for each worker."""
    import pyarrow.parquet as pq
    from pyarrow import fs

    files, top = fs.FileSystem.from_uri(path)
    return Model.from_counts(pq.read_table(top, columns=["lang", "key", "c"], filesystem=files))


def base_counts(words: Words) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of each text."""
    n = len(words.offsets) - 1
    per = lambda at: np.bincount(at, minlength=n).astype(np.int64)
    data, off = words.data, words.offsets
    sums = lambda x: np.concatenate([[0], np.cumsum(x, dtype=np.int64)])
    whole = sums((data & 0xC0) != 0x80)
    chars = whole[words.end] - whole[words.start]
    symbols = sums(SYMBOLS[data])
    out = {"n_words": per(words.doc), "word_chars": np.bincount(words.doc, chars, n).astype(np.int64), "n_symbols": symbols[off[1:]] - symbols[off[:-1]]}
    # lines: those that hold a word
    breaks = np.flatnonzero(data == 10)
    size = off[1:] - off[:-1]
    begin = np.unique(np.concatenate([off[:-1][size > 0], breaks + 1]))
    begin = begin[begin < len(data)]
    end = np.minimum(np.append(breaks, len(data))[np.searchsorted(breaks, begin)], off[np.searchsorted(off, begin, "right")])
    full = np.searchsorted(words.start, end) > np.searchsorted(words.start, begin)
    begin, end = begin[full], end[full]
    doc = np.searchsorted(off, begin, "right") - 1
    out["n_dup_lines"] = per(doc[_again(words.span_hash(begin, end), doc, first=False)])
    # words in windows of eight that occur again
    gram, at = words.grams(8)
    again = at[_again(gram, words.doc[at], first=True)]
    mark = np.zeros(len(words.hash) + 9, np.int32)
    np.add.at(mark, again, 1)
    np.add.at(mark, again + 8, -1)
    out["n_repeat_words"] = per(words.doc[np.cumsum(mark)[: len(words.hash)] > 0])
    return out


def _again(value: np.ndarray, doc: np.ndarray, first: bool) -> np.ndarray:
    """Where a value occurs more than once in its text; without `first`, the earliest occurrence is left out."""
    key = mix(value + doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(key, kind="stable")
    key = key[order]
    same = np.zeros(len(key) + 1, bool)
    same[1:-1] = key[1:] == key[:-1]
    return np.sort(order[same[:-1] | same[1:]] if first else order[same[:-1]])


MEASURES = f"{BASE}, digest binary, logp double"


def measures(docs, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang"):
    """MEASURES: the base counts, the text's MD5 and, with the counts' path, its log-probability."""

    def run(batches):
        model = model_at(path) if path else None
        for part in slices(batches, "t"):
            words = Words(part.column(2))
            base = base_counts(words)
            size = words.offsets[1:] - words.offsets[:-1]
            logp = np.zeros(len(size))
            for lang, which in _languages(part.column(1)).items() if model else ():
                keys, n = keys_of(words.data, words.offsets, which)
                if len(keys):  # each text is summed by itself, so that its value doesn't depend on the others
                    logp[which[n > 0]] = np.add.reduceat(model.logp(lang, keys), (np.cumsum(n) - n)[n > 0])
            values = pa.array(logp) if model else pa.nulls(len(size), pa.float64())
            cols = [part.column(0), as_text(part.column(1)), *(pa.array(base[c]) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), pa.array(size), digests(words.data, words.offsets), values]
            yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in MEASURES.split(", ")])

    ready(docs.sparkSession)
    return _rows(docs, id_col, lang_col, text_col).mapInArrow(run, MEASURES)


def digests(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    """MD5 of each text: equal ones, equal keys, whatever their ids."""
    return pa.array([hashlib.md5(data[a:z], usedforsecurity=False).digest() for a, z in zip(offsets.tolist(), offsets[1:].tolist(), strict=False)], pa.binary())


def _rows(docs, id_col, lang_col, text_col):
    return docs.select(docs[id_col].cast("long").alias("i"), F.coalesce(docs[lang_col].cast("string"), F.lit("")).alias("l"), docs[text_col].alias("t"))


def joined_logp(docs, model, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang"):
    """lang, digest, logp by a shuffled join of n-gram counts to the model's table, for models too large for a worker:
    the sum over all copies of a text.

    The texts must be among those the model was counted on, so that every n-gram is in it.
    """

    def run(batches):
        for part in slices(batches, "t"):
            data, off = raw(part.column(2))
            own = digests(data, off)
            for lang, which in _languages(part.column(1)).items():
                for d in which.tolist():
                    key, n = counted(keys_of(data, off, np.array([d]))[0])
                    if len(key):
                        one = pa.array(np.zeros(len(key), np.int32))
                        yield pa.RecordBatch.from_arrays([own.slice(d, 1).take(one), pa.array([lang]).take(one), pa.array(key), pa.array(n)], names=["digest", "lang", "key", "k"])

    rows = _rows(docs, id_col, lang_col, text_col).mapInArrow(run, "digest binary, lang string, key long, k long")
    top = model.where(F.col("n") == ORDER).select("lang", "key", "logp")
    return rows.join(top, ["lang", "key"]).groupBy("lang", "digest").agg(F.sum(F.col("k") * F.col("logp").cast("double")).alias("logp"))


def bands(scored, below: float = BELOW, above: float = ABOVE):
    """lang, middle, below, above from the quartiles of `bits`: those of a histogram, counted before it is dealt by language."""
    step = F.floor(F.col("bits") * STEPS)
    counts = scored.where("bits IS NOT NULL").groupBy("lang", step.alias("at")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("lang")  # as many rows as a language has steps
    upto = counts.select("lang", "at", F.sum("n").over(w.orderBy("at")).alias("upto"), F.sum("n").over(w).alias("total"))
    at = lambda q: (F.min(F.when(F.col("upto") >= q * F.col("total"), F.col("at"))) / STEPS).alias(f"q{int(100 * q)}")
    q = upto.groupBy("lang").agg(at(0.25), at(0.5), at(0.75))
    side = lambda a, b, k: F.greatest((F.col(a) - F.col(b)) * k, F.lit(LEAST_WIDTH))
    return q.select("lang", F.col("q50").alias("middle"), side("q50", "q25", below).alias("below"), side("q75", "q50", above).alias("above"))


def judge(docs, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", most: int = MOST_ENTRIES, below: float = BELOW, above: float = ABOVE):
    """One row per text: the base counts, bits a byte, perplexity, the language's band, the verdict, and the text's MD5."""
    counts, path = written_at(ngram_counts(docs, text_col, lang_col), "ngrams")
    if counts.count() <= most:
        scored = measures(docs, path, id_col, text_col, lang_col)
    else:
        model = written(kneser_ney(counts), "model")
        scored = written(measures(docs, None, id_col, text_col, lang_col), "measured").drop("logp")
        copies = scored.groupBy("lang", "digest").agg(F.count("*").alias("copies"))
        logp = joined_logp(docs, model, id_col, text_col, lang_col).join(copies, ["lang", "digest"]).select("lang", "digest", (F.col("logp") / F.col("copies")).alias("logp"))
        scored = scored.join(logp, ["lang", "digest"], "left")
    bits = F.when(F.col("n_bytes") > 0, F.round(-F.col("logp") / F.log(F.lit(2.0)) / F.col("n_bytes"), 6))
    scored = written(scored.withColumn("bits", bits).drop("logp"), "scored")
    limits = written(bands(scored, below, above), "bands")
    limits = F.broadcast(limits) if limits.count() <= MOST_LANGUAGES else limits.hint("merge")
    wide = F.when(F.col("n_bytes") > 0, F.sqrt(1 + F.lit(LENGTH) / F.col("n_bytes")))
    out = scored.join(limits, "lang", "left").withColumn("low_bits", F.col("middle") - F.col("below") * wide).withColumn("high_bits", F.col("middle") + F.col("above") * wide)
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    fits = F.coalesce(F.col("bits").between(F.col("low_bits"), F.col("high_bits")), F.lit(True))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & fits).alias("kept"), "lang", "n_bytes", "bits", F.pow(F.lit(2.0), "bits").alias("perplexity"), "low_bits", "high_bits", "digest")


def op10_quality(spark, sf_dir):
    return judge(table(spark, sf_dir, "documents")).drop("digest")
