"""Prompt texts: three roles, an end token, and the answer for slices without a gold table."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

NONE = "#None#"
END = "<end>"
SYSTEM = {
    "link": "You choose the tables that a question needs.",
    "slice": "You choose the tables that a question needs from a part of the database, or say #None#.",
    "sql": "You write one SQL query that answers a question over the given tables.",
}
USER = {
    "link": "Tables: {schema}\nQuestion: {question}",
    "slice": "Tables: {schema}\nAlready chosen: {history}\nQuestion: {question}",
    "sql": "Tables: {schema}\nQuestion: {question}",
}


def user(kind: str, **parts: Column) -> Column:
    """The user's part of a prompt as a Column."""
    out, rest = [], USER[kind]
    for name in ("schema", "history", "question"):
        mark = "{" + name + "}"
        if mark in rest:
            before, rest = rest.split(mark, 1)
            out += [F.lit(before), F.coalesce(parts[name], F.lit(""))]
    return F.concat(*out, F.lit(rest))


def answer(tables: Column) -> Column:
    """The assistant's part: table names, or the mark for none."""
    return F.when(F.size(tables) == 0, F.lit(NONE)).otherwise(F.array_join(tables, ", "))


def render(kind: str, user_text: Column, assistant: Column) -> Column:
    """The whole training text; only what follows the last role mark bears the loss."""
    return F.concat(F.lit(f"<system>{SYSTEM[kind]}<user>"), user_text, F.lit("<assistant>"), assistant, F.lit(END))
