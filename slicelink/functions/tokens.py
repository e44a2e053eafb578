"""Token counters of schema texts: word pieces, characters over four, and a byte-pair vocabulary learned on catalogs."""

from __future__ import annotations

import re
from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

WORD = r"[A-Za-z]+|[0-9]+|[^\sA-Za-z0-9]"


def count(col: str | Column, kind: str = "word") -> Column:
    """Number of tokens of a text: `word` (letter runs, digit runs, single other characters) or `char4` (a quarter of its characters, rounded up)."""
    c = F.col(col) if isinstance(col, str) else col
    if kind == "word":
        return F.size(F.regexp_extract_all(c, F.lit(WORD), 0))
    if kind == "char4":
        return F.ceil(F.length(c) / 4).cast("int")
    raise ValueError(f"unknown token kind: {kind}")


class Merges:
    """A byte-pair vocabulary: merges in order of learning."""

    def __init__(self, merges: list[tuple[str, str]]):
        self.merges, self.rank = merges, {p: i for i, p in enumerate(merges)}

    def split(self, word: str) -> list[str]:
        parts = list(word)
        while len(parts) > 1:
            best, at = min((self.rank.get(p, len(self.rank)), i) for i, p in enumerate(zip(parts, parts[1:], strict=False)))
            if best == len(self.rank):
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def count(self, text: str) -> int:
        return sum(len(self.split(w)) for w in re.findall(WORD, text or ""))


def train_bpe(df: DataFrame, text_col: str, vocab: int = 200) -> Merges:
    """Learn merges on the word counts of a catalog's texts.

    The counts are a distributed aggregate; what reaches the driver is the distinct words of schema texts, which the
    number of tables bounds.
    """
    words = df.select(F.explode(F.regexp_extract_all(F.col(text_col), F.lit(WORD), 0)).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    left = {tuple(r.w): r.n for r in words.collect()}
    merges: list[tuple[str, str]] = []
    while len(merges) < vocab:
        pairs: Counter = Counter()
        for parts, n in left.items():
            for p in zip(parts, parts[1:], strict=False):
                pairs[p] += n
        if not pairs:
            break
        best = min(pairs, key=lambda p: (-pairs[p], p))
        merges.append(best)
        new: dict = {}
        for parts, n in left.items():
            out, i = [], 0
            while i < len(parts):
                if tuple(parts[i : i + 2]) == best:
                    out.append(parts[i] + parts[i + 1])
                    i += 2
                else:
                    out.append(parts[i])
                    i += 1
            new[tuple(out)] = new.get(tuple(out), 0) + n
        left = new
    return Merges(merges)


def bpe_counter(merges: Merges):
    """An Arrow-batched function of a text column."""

    @F.pandas_udf(T.IntegerType())
    def bpe_count(texts: pd.Series) -> pd.Series:
        return texts.map(merges.count).astype("int32")

    return bpe_count
