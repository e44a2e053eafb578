"""N-gram Jaccard self-join of documents by chosen paths.

A document is the set of its five-word shingles (all words at once, where it has fewer). Exact copies are first
collapsed to one text. A set is embedded in `COORDINATES` min-wise tokens; a run then splits the collection again and
again: at each node two tokens are sampled, the same ones for all sets in it, and sets that share a sampled token go
on together. After `DEPTH` splits a node with at most `BLOCK` sets is a small bucket. A larger one is compared at once
if its sets are alike (each and the next one of a shuffled order share tokens as sets of similarity `CLOSE` do), and
split `DEPTH` times more if not, up to `ROUNDS` times in all. A pair of similarity s is lost by a run with the extinction
probability of that branching process, which hardly grows with depth, so the number of runs follows from the target
recall.

Sets of a small bucket whose tokens agree with those of no other one in it to `AGREE` are dropped (at a similarity of
0.8 that loses one pair in 10 ** 7). What is left is compared by brute force on the exact shingle sets: buckets that
common sets tie to each other as a whole, in pairs of blocks of about `WIDE` sets, where that sends a set to no more
places than its buckets would, and bucket by bucket where not; there a pair counts in the first bucket that holds both.
Nodes of many sets that are alike are tied to dense groups, which are compared in pairs of blocks too: nearly every
pair of them is a link that has to be counted. No pair is emitted, and no task holds more than two blocks.

Defined results: null text is an empty one; texts without words have no shingles and no links, but equal ones are
copies; copies share class and links; a link counts for different texts only, once for each text, whatever the ids: a
row with a null or repeated id is judged by its text, and class_id is the smallest id that is known of the class (null
where none is); an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from .common import Words, mix, raw, ready, slices, table, written
from .components import components

SHINGLE, SIMILARITY, RECALL = 5, 0.8, 0.999
COORDINATES, DEPTH, WIDTH, BLOCK, WIDE, CLOSE, ROUNDS, AGREE = 64, 4, 2, 96, 512, 0.65, 3, 0.5
#: Sets of a node that one task judges; a larger node is judged in as many parts as it takes.
JUDGED = 4096
_U = np.uint64
_XOR = mix(np.arange(1, COORDINATES + 1, dtype=_U) * _U(0x9E3779B97F4A7C15))
_MUL = mix(_XOR) | _U(1)


def runs_for(recall: float = RECALL, similarity: float = SIMILARITY, depth: int = DEPTH, width: int = WIDTH) -> int:
    """Runs after which a pair of that similarity is in a common bucket with at least that probability."""
    lost = 0.0
    for _ in range(depth):
        lost = (1 - similarity + similarity * lost) ** width
    return max(1, math.ceil(math.log(1 - recall) / math.log(lost)))


def shingles(words: Words, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hash, text) of the distinct shingles, by text."""
    gram, at = words.grams(size)
    doc = words.doc[at]
    count = np.diff(words.first)
    few = np.flatnonzero((count > 0) & (count < size))
    if len(few):
        gram = np.concatenate([gram, words.span_hash(words.start[words.first[few]], words.end[words.first[few + 1] - 1])])
        doc = np.concatenate([doc, few])
    order = np.lexsort((gram, doc))
    gram, doc = gram[order], doc[order]
    keep = np.ones(len(gram), bool)
    keep[1:] = (gram[1:] != gram[:-1]) | (doc[1:] != doc[:-1])
    return gram[keep], doc[keep]


def signatures(gram: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Min-wise tokens (texts, COORDINATES); first: where each text's shingles begin, none empty."""
    out = np.empty((len(first), COORDINATES), _U)
    with np.errstate(over="ignore"):
        for j in range(COORDINATES):
            out[:, j] = np.minimum.reduceat((gram ^ _XOR[j]) * _MUL[j], first)
    return out


def roots(n: int, runs: int) -> np.ndarray:
    """The node of each run that holds everything, for n sets."""
    return np.broadcast_to(mix(np.arange(1, runs + 1, dtype=_U) * _U(0xA24BAED4963EE407)), (n, runs))


def paths(sig: np.ndarray, node: np.ndarray, depth: int = DEPTH, width: int = WIDTH) -> np.ndarray:
    """The nodes a set is in after `depth` more splits of each node (texts, nodes): (texts, nodes * width ** depth)."""
    rows = np.arange(len(sig))[:, None]
    with np.errstate(over="ignore"):
        for _ in range(depth):
            parts = []
            for c in range(width):
                at = mix(node + _U(c + 1) * _U(0x9E3779B97F4A7C15)) % _U(COORDINATES)
                parts.append(mix(node ^ mix(sig[rows, at.astype(np.int64)] + (at << _U(1)) + _U(c))))
            node = np.concatenate(parts, 1)
    return node


SKETCH = "u long, doc_id long, digest binary, n_shingles int, sig binary"


def sketches(docs, id_col: str = "doc_id", text_col: str = "text"):
    """SKETCH: a number of the row (unique in a written table), its text's MD5, and the upper halves of its min-wise tokens (null without shingles)."""

    def run(batches):
        from pyspark import TaskContext

        u = TaskContext.get().partitionId() << 33
        for part in slices(batches, "t"):
            words = Words(part.column(1))
            gram, doc = shingles(words)
            size = np.bincount(doc, minlength=part.num_rows)
            have = np.flatnonzero(size)
            sig = (signatures(gram, np.searchsorted(doc, have)) >> _U(32)).astype(np.uint32) if len(have) else np.zeros((0, COORDINATES), np.uint32)
            offsets = np.concatenate([[0], np.cumsum(np.where(size > 0, 4 * COORDINATES, 0))]).astype(np.int32)
            sig = pa.Array.from_buffers(pa.binary(), part.num_rows, [None, pa.py_buffer(offsets), pa.py_buffer(sig.tobytes())])
            data, off = words.data, words.offsets
            digest = [hashlib.md5(data[a:b], usedforsecurity=False).digest() for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(u + np.arange(part.num_rows)), part.column(0), pa.array(digest, pa.binary()), pa.array(size.astype(np.int32)), sig], names=[x.split()[0] for x in SKETCH.split(", ")])
            u += part.num_rows

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, SKETCH)


def _splits(runs: int):
    """Rows (v, sig, nodes; none at first) -> v, paths: the nodes after DEPTH more splits."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            sig = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint32).reshape(-1, COORDINATES).astype(_U)
            if batch.num_columns == 2:
                out = paths(sig, roots(len(sig), runs))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1, dtype=np.int32) * out.shape[1]), pa.array(out.ravel().view(np.int64)))
            else:
                nodes = batch.column(2)
                size = np.diff(nodes.offsets.to_numpy())
                own = nodes.flatten().to_numpy().view(_U)
                out = paths(sig[np.repeat(np.arange(len(size)), size)], own[:, None])
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size) * out.shape[1]]).astype(np.int32)), pa.array(out.ravel().view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], names=["v", "paths"])

    return run


def _agreement(batches):
    """Rows (p, s, sig) sorted by p, s: for each p the neighbours within its s, and the tokens in which they agree."""
    held, before = None, None
    for batch in batches:
        if not batch.num_rows:
            continue
        sig = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint32).reshape(-1, COORDINATES)
        key = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy()], 1)
        if held is not None:
            key, sig = np.concatenate([held, key]), np.concatenate([before, sig])
        held, before = key[-1:], sig[-1:]
        node, at = np.unique(key[:, 0], return_inverse=True)
        pair = np.flatnonzero((key[1:] == key[:-1]).all(1))
        agreed = (sig[pair + 1] == sig[pair]).sum(1)
        yield pa.RecordBatch.from_arrays([pa.array(node), *(pa.array(np.bincount(at[pair], w, len(node)).astype(np.int64)) for w in (None, agreed))], names=["p", "pairs", "agreed"])


def alike_nodes(large, first):
    """p, alike of nodes (p, v, n: their size): whether neighbours in the order of a hash agree as sets of similarity `CLOSE` do."""
    parts = int(first.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = large.select("p", "v", "n").join(first.select("v", "sig").hint("merge"), "v")
    rows = rows.select("p", F.pmod(F.xxhash64("v"), F.ceil(F.col("n") / JUDGED)).alias("s"), F.xxhash64(F.lit(1), "v").alias("h"), "sig")
    pairs = rows.repartition(parts, "p", "s").sortWithinPartitions("p", "s", "h").select("p", "s", "sig").mapInArrow(_agreement, "p long, pairs long, agreed long")
    return pairs.groupBy("p").agg((F.sum("agreed") >= F.lit(CLOSE * COORDINATES) * F.sum("pairs")).alias("alike"))


def buckets(first, runs: int, block: int = BLOCK):
    """The sets (v, sig) split: vs, the distinct small buckets as sorted lists; and m, v: the sets of nodes that are dense, with the node's first."""
    none = first.sparkSession.createDataFrame([], "m long, v long")
    small, dense, rows = None, none, first.select("v", "sig")
    for k in range(1, ROUNDS + 1):
        inside = rows.mapInArrow(_splits(runs), "v long, paths array<long>").select("v", F.explode("paths").alias("p"))
        count = inside.groupBy("p").agg(F.count("*").alias("n"), F.min("v").alias("m")).where("n > 1")
        # merge joins at every size: what is small here grows with the input
        shared = written(inside.join(count.hint("merge"), "p"), "shared")
        here = shared.where(F.col("n") <= block).groupBy("p").agg(F.array_sort(F.collect_list("v")).alias("vs")).select("vs")
        small = here if small is None else small.union(here)
        large = shared.where(F.col("n") > block)
        if large.isEmpty():
            break
        large = written(large.join(alike_nodes(large, first).hint("merge"), "p").select("p", "v", "m", (F.col("alike") | F.lit(k == ROUNDS)).alias("alike")), "large")
        dense = dense.union(large.where("alike").select("m", "v").distinct())
        rows = large.where("NOT alike").groupBy("v").agg(F.collect_list("p").alias("nodes"))  # as many as a text's own splits
        if rows.isEmpty():
            break
        rows = rows.join(first.hint("merge"), "v").select("v", "sig", "nodes")
    return written(small.distinct(), "buckets"), dense


def _plausible(batches):
    """Rows (c, v, sig) sorted by c, v: vs, the sets of each c whose tokens agree with those of another one to `AGREE`."""
    key, vs, sigs, out = None, [], [], []

    def settle():
        sig = np.frombuffer(b"".join(sigs), np.uint32).reshape(-1, COORDINATES)
        agree = (sig[:, None, :] == sig[None, :, :]).sum(2)
        np.fill_diagonal(agree, 0)
        keep = np.flatnonzero(agree.max(1) >= AGREE * COORDINATES)
        if len(keep):
            out.append([vs[i] for i in keep])

    for batch in batches:
        for c, v, sig in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if c != key:
                if len(vs) > 1:
                    settle()
                key, vs, sigs = c, [], []
            vs.append(v)
            sigs.append(sig)
        if len(out) > 10_000:
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.int64()))], names=["vs"])
            out = []
    if len(vs) > 1:
        settle()
    yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.int64()))], names=["vs"])


def owners(member, groups):
    """v, us, d: a row a set, with its units c of member (c, v) as a sorted list and its dense group; the join thus makes as many rows as there are sets."""
    of = member.groupBy("v").agg(F.array_sort(F.collect_list("c")).alias("us"))  # as many as a text's own splits
    return of.join(groups.select("v", F.col("c").alias("d")).hint("merge"), "v", "left").select("v", "us", "d")


def units(first, vs, dense, block: int = WIDE):
    """v, kind, c, nb, b, us, d: in which units (kind, c) a set is compared; nb blocks of the unit and the set's own; us: all units of it where pairs may meet in several; d: its dense group."""
    groups = components(dense.select(F.col("v").alias("a"), F.col("m").alias("b")))
    # a bucket inside a dense group has no pair of its own
    member = owners(vs.select(F.xxhash64("vs").alias("c"), F.explode("vs").alias("v")), groups).select("v", F.coalesce("d", "v").alias("whose"), F.explode("us").alias("c"))
    apart = member.groupBy("c").agg(F.min("whose").alias("x"), F.max("whose").alias("y")).where("x <> y").select("c")
    member = member.select("c", "v").join(apart.hint("merge"), "c", "left_semi").join(first.select("v", "sig").hint("merge"), "v").select("c", "v", "sig")
    parts = int(first.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    vs = written(member.repartition(parts, "c").sortWithinPartitions("c", "v").mapInArrow(_plausible, "vs array<long>").distinct(), "apart")
    size = groups.groupBy("c").agg(F.ceil(F.count("*") / block).cast("int").alias("nb"))
    none = F.lit(None).cast("array<long>")
    thick = groups.join(size, "c").select("v", F.lit(2).alias("kind"), "c", "nb", F.pmod(F.xxhash64("v"), F.col("nb")).cast("int").alias("b"), none.alias("us"), F.lit(None).cast("long").alias("d"))
    tied = components(vs.select(F.col("vs")[0].alias("a"), F.explode("vs").alias("b")))
    # tied buckets are compared as a whole, in blocks, where that sends a set to no more places than its buckets would
    often = vs.groupBy(F.col("vs")[0].alias("v")).agg(F.sum(F.size("vs")).alias("n"))
    size = tied.join(often.hint("merge"), "v", "left").groupBy("c").agg(F.ceil(F.count("*") / block).cast("int").alias("nb"), (F.sum("n") / F.count("*")).alias("places"))
    whole = F.col("nb") <= F.greatest("places", F.lit(1.0))
    one = tied.join(size.where(whole).hint("merge"), "c").select("v", F.lit(0).alias("kind"), "c", "nb", F.pmod(F.xxhash64("v"), F.col("nb")).cast("int").alias("b"), none.alias("us"))
    wide = tied.join(size.where(~whole).hint("merge"), "c").select(F.col("v").alias("a"))
    lists = vs.withColumn("a", F.col("vs")[0]).join(wide.hint("merge"), "a", "left_semi").select(F.xxhash64("vs").alias("c"), F.explode("vs").alias("v")).distinct()
    of = owners(lists, groups)
    many = of.select("v", F.lit(1).alias("kind"), F.explode("us").alias("c"), F.lit(1).alias("nb"), F.lit(0).alias("b"), "us", "d")
    thin = one.join(groups.select("v", F.col("c").alias("d")).hint("merge"), "v", "left").unionByName(many)
    return thick.unionByName(thin.select("v", "kind", "c", "nb", "b", "us", "d"))


def intersections(gram: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """Shared shingles of each two of n texts."""
    order = np.argsort(gram, kind="stable")
    value, doc = gram[order], doc[order]
    new = np.concatenate([[True], value[1:] != value[:-1]]) if len(value) else np.zeros(0, bool)
    kind = np.cumsum(new) - 1
    often = np.bincount(kind)[kind] > 1 if len(kind) else np.zeros(0, bool)
    kind, doc = kind[often], doc[often]
    out = np.zeros((n, n))
    if not len(kind):
        return out
    kind = np.cumsum(np.concatenate([[True], kind[1:] != kind[:-1]])) - 1
    wide = max(1, (1 << 22) // n)
    for a in range(0, int(kind[-1]) + 1, wide):
        lo, hi = np.searchsorted(kind, [a, a + wide])
        m = np.zeros((n, min(wide, int(kind[-1]) + 1 - a)), np.float32)
        m[doc[lo:hi], kind[lo:hi] - a] = 1
        out += m @ m.T
    return out


def compare(ids: list[int], left: np.ndarray, right: np.ndarray, gram: np.ndarray, doc: np.ndarray, similarity: float, elsewhere=None, first=None) -> list[tuple[int, int, int]]:
    """(id, links found here, smallest id it is linked with here, through others too) of those with links; compared are the pairs with one
    text of `left` and one of `right` (masks; the same mask: all pairs), without the pairs of the mask `elsewhere`; of the links (x, y) those for which `first` holds."""
    n = len(ids)
    size = np.bincount(doc, minlength=n).astype(np.float64)
    both = intersections(gram, doc, n)
    link = both >= similarity * (size[:, None] + size[None, :] - both) - 1e-9
    link &= (left[:, None] & right[None, :]) | (right[:, None] & left[None, :])
    link &= (size > 0)[:, None]
    np.fill_diagonal(link, False)
    if elsewhere is not None:
        link &= ~elsewhere
    for x, y in np.argwhere(np.triu(link)).tolist() if first else ():
        if not first(x, y):
            link[x, y] = link[y, x] = False
    count = link.sum(1)
    root = np.array(ids, np.int64)
    while True:  # the smallest id spreads over the links
        best = np.where(link, root[None, :], np.iinfo(np.int64).max).min(1, initial=np.iinfo(np.int64).max)
        new = np.minimum(root, best)
        if (new == root).all():
            break
        root = new
    return [(ids[k], int(count[k]), int(root[k])) for k in np.flatnonzero(count)]


def _blocks(batches, similarity):
    """Rows (kind, c, x, y, b, v, t, us, d) sorted by kind, c, x, y, v: those of one key are compared."""
    schema = pa.schema([("v", pa.int64()), ("links", pa.int64()), ("root", pa.int64())])
    key, held, found = None, [], []

    def settle():
        rows = pa.Table.from_batches(held).combine_chunks()
        v = rows.column("v").to_numpy()
        rows = rows.take(pa.array(np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]]))))  # equal rows of one id
        words = Words(rows.column("t").combine_chunks())
        gram, doc = shingles(words)
        b, d = rows.column("b").to_numpy(), rows.column("d").fill_null(-1).to_numpy()
        elsewhere = (d[:, None] == d[None, :]) & (d >= 0)  # pairs of one dense group
        first = None
        if key[0] == 1:
            us = [set(x) for x in rows.column("us").to_pylist()]
            first = lambda x, y: min(us[x] & us[y]) == key[1]
        return compare(rows.column("v").to_pylist(), b == key[2], b == key[3], gram, doc, similarity, elsewhere, first)

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(j).to_numpy() for j in range(4)]
        new = np.ones(batch.num_rows, bool)
        new[1:] = np.any([c[1:] != c[:-1] for c in cols], 0)
        starts = [*np.flatnonzero(new).tolist(), batch.num_rows]
        for a, z in zip(starts, starts[1:], strict=False):
            now = tuple(int(c[a]) for c in cols)
            if now != key:
                if held:
                    found += settle()
                key, held = now, []
            held.append(batch.slice(a, z - a))
        if len(found) > 10_000:
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], schema=schema)
            found = []
    if held:
        found += settle()
    if found:
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], schema=schema)


def similar(docs, similarity: float = SIMILARITY, recall: float = RECALL, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, wide: int = WIDE):
    """One row per document: class_id (the smallest id of its class), copy_of (the smallest id with the same text),
    n_copies, n_links (different texts of at least that similarity), n_shingles, digest (the text's MD5), class_key (a number of
    the class, in this result)."""
    texts = docs.select(docs[id_col].cast("long").alias("i"), F.coalesce(docs[text_col], F.lit("")).alias("t"))
    sketch = written(sketches(docs, id_col, text_col), "sketches")
    same = written(sketch.groupBy("digest").agg(F.min("u").alias("v"), F.min("doc_id").alias("r"), F.count("*").alias("n_copies")), "copies")
    first = sketch.where("n_shingles > 0").select(F.col("u").alias("v"), "sig").join(same.select("v").hint("merge"), "v", "left_semi")
    first = written(first, "texts")
    own = units(first, *buckets(first, runs_for(recall, similarity), block), wide)
    own = own.join(same.select("v", "r", "digest").hint("merge"), "v")
    texts = texts.withColumn("h", F.unhex(F.md5("t")))
    rows = texts.join(own.hint("merge"), (F.col("h") == F.col("digest")) & F.col("i").eqNullSafe(F.col("r")))
    rows = rows.select("kind", "c", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)).alias("o"), "b", "v", "t", "us", "d")
    rows = rows.select("kind", "c", F.least("b", "o").alias("x"), F.greatest("b", "o").alias("y"), "b", "v", "t", "us", "d")
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(parts, "kind", "c", "x", "y").sortWithinPartitions("kind", "c", "x", "y", "v")
    found = written(rows.mapInArrow(lambda batches: _blocks(batches, similarity), "v long, links long, root long"), "links")
    classes = components(found.select(F.col("v").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("v").agg(F.sum("links").alias("n_links"))
    linked = written(classes.join(links, "v").join(same.select("v", "r").hint("merge"), "v"), "linked")
    names = linked.groupBy("c").agg(F.min("r").alias("class_id"))
    of = same.join(linked.join(names, "c").select("v", "class_id", "n_links", "c").hint("merge"), "v", "left")
    of = of.select("digest", F.coalesce("class_id", "r").alias("class_id"), F.col("r").alias("copy_of"), "n_copies", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("c", "v").alias("class_key"))
    return sketch.select("doc_id", "digest", "n_shingles").join(of, "digest").select("doc_id", "class_id", "copy_of", "n_copies", "n_links", "n_shingles", "digest", "class_key")


def op7_jaccard(spark, sf_dir):
    return similar(table(spark, sf_dir, "documents")).drop("digest", "class_key")
