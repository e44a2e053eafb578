"""Functions for SQL users: token counts, a packing table function, F1 of two table sets."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..functions.tokens import WORD


@udtf(returnType="slice_id int, table_name string, n_tokens int")
class PackSlices:
    """Tables in order with their tokens -> slices below the cap, as slicing.pack() makes them."""

    def eval(self, tables: list, tokens: list, cap: int):
        total, slice_id = 0, 0
        for name, n in zip(tables or [], tokens or [], strict=False):
            if not slice_id or total + n >= cap:
                slice_id, total = slice_id + 1, n
            else:
                total += n
            yield slice_id, name, n


@udtf(returnType="table_name string, word string, in_name boolean")
class ExplainLink:
    """Which words of a question each table's name or columns hold; schemas are rendered descriptions."""

    def eval(self, question: str, schemas: list):
        words = {w[:-1] if len(w) > 3 and w.endswith("s") else w for w in re.findall("[a-z]+|[0-9]+", (question or "").lower())}
        for schema in schemas or []:
            name, _, rest = schema.partition("(")
            for own, text in ((True, name), (False, rest)):
                for w in sorted({x[:-1] if len(x) > 3 and x.endswith("s") else x for x in re.findall("[a-z]+|[0-9]+", text.lower())} & words):
                    yield name, w, own


def register(spark: SparkSession) -> None:
    """token_count(text), link_f1(pred, gold) as SQL functions, pack_slices(tables, tokens, cap) and explain_link(question, schemas) as table functions."""
    pattern = WORD.replace("\\", "\\\\").replace("'", "\\'")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION token_count(t STRING) RETURNS INT RETURN size(regexp_extract_all(t, '{pattern}', 0))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION link_f1(p ARRAY<STRING>, g ARRAY<STRING>) RETURNS DOUBLE RETURN CASE WHEN size(p) + size(g) = 0 THEN 1D ELSE 2D * size(array_intersect(p, g)) / (size(p) + size(g)) END")
    spark.udtf.register("pack_slices", PackSlices)
    spark.udtf.register("explain_link", ExplainLink)
