"""Sources and sinks: any format with a schema and a bad-record column, DDL directories, example files, runs by id."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader


def read_any(spark: SparkSession, path: str, fmt: str, schema: str, bad: str = "_corrupt_record") -> DataFrame:
    """CSV, JSON, text, ORC or Parquet with an explicit schema; rows that don't fit are kept in `bad` where the format can."""
    if fmt in ("csv", "json"):
        return spark.read.format(fmt).schema(f"{schema}, {bad} string").options(mode="PERMISSIVE", columnNameOfCorruptRecord=bad, header="true").load(path)
    return spark.read.format(fmt).schema(schema).load(path)


_CREATE = re.compile(r"CREATE\s+TABLE\s+(?:IF\s+NOT\s+EXISTS\s+)?[\"`]?(\w+)[\"`]?\s*\((.*?)\)\s*;", re.I | re.S)
_KEY = re.compile(r"FOREIGN\s+KEY\s*\(([^)]*)\)\s*REFERENCES\s+[\"`]?(\w+)[\"`]?\s*\(([^)]*)\)", re.I)


def parse_ddl(text: str) -> list[tuple[str, list[tuple[str, str]], list[tuple[list[str], str, list[str]]]]]:
    """(table, [(column, type)], [(columns, referenced table, referenced columns)]) of CREATE TABLE statements."""
    names = lambda s: [x.strip().strip('"`') for x in s.split(",")]
    out = []
    for table, body in _CREATE.findall(text):
        keys = [(names(a), ref, names(b)) for a, ref, b in _KEY.findall(body)]
        cols, depth, part = [], 0, ""
        for c in _KEY.sub("", body) + ",":
            depth += (c in "(<") - (c in ")>")
            if c == "," and depth == 0:
                m = re.match(r"\s*[\"`]?(\w+)[\"`]?\s+(\w+(?:\s*[(<][^,]*[)>])?)", part)
                if m and m[1].upper() not in ("PRIMARY", "FOREIGN", "UNIQUE", "CONSTRAINT", "CHECK"):
                    cols.append((m[1], m[2].lower()))
                part = ""
            else:
                part += c
        out.append((table, cols, keys))
    return out


class DdlDirectory(DataSource):
    """format("ddl_dir"): one row a table of the .sql files in a directory that the workers can open."""

    @classmethod
    def name(cls):
        return "ddl_dir"

    def schema(self):
        return "file string, table_name string, columns array<struct<name:string,type:string>>, fks array<struct<cols:array<string>,ref_table:string,ref_cols:array<string>>>"

    def reader(self, schema):
        return DdlReader(self.options)


class DdlReader(DataSourceReader):
    def __init__(self, options):
        self.path = options["path"]

    def partitions(self):
        import os

        from pyspark.sql.datasource import InputPartition

        return [InputPartition(os.path.join(self.path, f)) for f in sorted(os.listdir(self.path)) if f.endswith(".sql")] or [InputPartition(None)]

    def read(self, partition):
        if partition.value:
            with open(partition.value) as f:
                for table, cols, keys in parse_ddl(f.read()):
                    yield (partition.value, table, cols, keys)


def read_ddl(spark: SparkSession, path: str) -> DataFrame:
    spark.dataSource.register(DdlDirectory)
    return spark.read.format("ddl_dir").option("path", path).load()


def write_examples(examples: DataFrame, path: str, fmt: str = "json", by=("variant",), rows: int = 100_000) -> None:
    """Training examples for a fine-tuner: a folder for each value of `by`, files of bounded rows."""
    examples.write.partitionBy(*by).option("maxRecordsPerFile", rows).mode("overwrite").format(fmt).save(path)


def write_run(result: DataFrame, path: str, run_id: str) -> None:
    """Write one run's rows; writing it again replaces them and no others."""
    from pyspark.sql import functions as F

    result.withColumn("run_id", F.lit(run_id)).write.partitionBy("run_id").option("partitionOverwriteMode", "dynamic").mode("overwrite").parquet(path)
