"""The corpus pipeline: quality rules, n-gram Jaccard join, substring dedup, personal data, packing.

Every stage takes all that the one before kept. All but the last return the columns of documents, n_chars set anew
where a stage changes texts. A verdict names a row by its doc_id and the MD5 of its text, so rows that share a doc_id
are judged one by one, and rows with a null doc_id like others; equal rows (doc_id and text) have the same verdict, and
one of them at most passes near_duplicates. Only repeated_passages leaves texts without a doc_id alone: they have no
place in the order by which the first holder of a passage keeps it.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from slicelink.llm.common import fresh_path, ready, slices, written
from slicelink.llm.jaccard import similar
from slicelink.llm.packing import pack
from slicelink.llm.passages import passages
from slicelink.llm.pii import redact
from slicelink.llm.quality import judge

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _told(docs, verdicts, how):
    """docs joined with verdicts (doc_id, digest, ...), which are named by doc_id and the text's MD5."""
    docs = docs.select(*COLUMNS, F.unhex(F.md5(F.coalesce("text", F.lit("")))).alias("_digest"))
    named = verdicts.withColumnsRenamed({"doc_id": "_id", "digest": "_of"}).hint("merge")  # at every size: verdicts grow with the input
    return docs.join(named, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_digest") == F.col("_of")), how)


def quality(spark, docs, sf_dir):
    """Rejected documents go."""
    return _told(docs, judge(docs).where(~F.col("kept")).select("doc_id", "digest"), "left_anti").select(COLUMNS)


def near_duplicates(spark, docs, sf_dir):
    """Of each group of similar documents the one with the smallest id stays (of equal ids that with the least MD5; null ids come last)."""
    rows = similar(docs).groupBy("class_key", "doc_id", "digest").agg(F.count("*").alias("same"))
    first = rows.groupBy("class_key").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "digest", "same")).alias("f"))
    first = written(first.select("f.doc_id", "f.digest", "f.same"), "first")
    kept = _told(docs, first, "inner")
    once = kept.where("same > 1").dropDuplicates(["doc_id", "_digest"])
    return kept.where("same = 1").select(COLUMNS).unionByName(once.select(COLUMNS))


def _cut(batches):
    """Rows (COLUMNS, spans): texts without their spans; a text that had some and has no word left goes."""
    import pyarrow as pa

    for part in slices(batches, "text"):
        spans = part.column(5).to_pylist()
        hit = [i for i, s in enumerate(spans) if s]
        if hit:
            texts, chars, keep = part.column(1).to_pylist(), part.column(4).to_pylist(), [True] * part.num_rows
            for i in hit:
                out, at = [], 0
                for s in sorted((x["start"], x["end"]) for x in spans[i]):
                    out.append(texts[i][at : max(at, s[0])])
                    at = max(at, s[1])
                texts[i] = "".join(out) + texts[i][at:]
                chars[i], keep[i] = len(texts[i]), bool(texts[i].strip(" \t\n\x0b\x0c\r"))
            part = part.set_column(1, "text", pa.array(texts, pa.string())).set_column(4, "n_chars", pa.array(chars, part.schema.field(4).type)).filter(pa.array(keep))
        yield part.select(COLUMNS)


def repeated_passages(spark, docs, sf_dir):
    """A passage stays in the first document that holds it and is cut from the others; one with nothing else goes."""
    found = passages(docs).groupBy("doc_id", "digest").agg(F.collect_set(F.struct("start", "end")).alias("spans"))  # as many as its own length allows
    return _told(docs, written(found, "spans"), "left").select(*COLUMNS, "spans").mapInArrow(_cut, docs.select(COLUMNS).schema)


def personal_data(spark, docs, sf_dir):
    """Personal data gives way to the name of its kind."""
    out = redact(docs.select(COLUMNS))
    return out.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast(docs.schema["n_chars"].dataType)).select(COLUMNS)


def packing(spark, docs, sf_dir):
    """Sequences of tokens."""
    return pack(docs)


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("repeated_passages", repeated_passages), ("personal_data", personal_data), ("packing", packing)]
#: Perplexities, alignments and the field's labels have no SQL; tests hold every stage against a plain version.
ORACLE_SQL = None


def run(spark, sf_dir):
    """Apply STAGES to documents; each result is written as Parquet and read again as the next one's docs."""
    docs = ready(spark).read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        path = fresh_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
