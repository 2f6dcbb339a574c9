"""Boundary-preserving token preprocessing, as column expressions; all narrow, none in Python.

A piece that is one name is split into its parts with visible joins, so that the split can be undone:
an underscore stays a token of its own, and a change of case gets the join mark.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Stands where a name changes case.
JOIN = "~"


def split_ident(col: Column) -> Column:
    """Tokens of a name: its parts and its underscores."""
    return F.split(F.trim(F.regexp_replace(col, "_", " _ ")), " +")


def split_camel(col: Column) -> Column:
    return F.regexp_replace(col, "([a-z0-9])([A-Z])", "$1 $2")


def _outside(col: Column, change) -> Column:
    """``change`` applied to the parts of a text outside quotes; linear in the text."""
    parts = F.split(col, "'")
    return F.array_join(F.transform(parts, lambda p, i: F.when(i % 2 == 0, change(p)).otherwise(p)), "'")


def space_sql(col: Column) -> Column:
    """Spaces around signs, dots and operators outside quotes, and none doubled."""
    spaced = lambda p: F.regexp_replace(F.regexp_replace(p, r"(<=|>=|<>|!=|[(),.=<>*+/-])", " $1 "), r"\s+", " ")
    return F.trim(_outside(col, spaced))


def apply(col: Column) -> Column:
    """Names in a text of SQL or schema, split reversibly, outside quotes."""
    cased = lambda p: F.regexp_replace(p, "([a-z0-9])([A-Z])", f"$1 {JOIN} $2")
    return _outside(col, lambda p: F.regexp_replace(cased(p), "(?<=[A-Za-z0-9])_(?=[A-Za-z0-9])", " _ "))


def restore(col: Column) -> Column:
    return _outside(col, lambda p: F.regexp_replace(F.regexp_replace(p, " _ ", "_"), f" {JOIN} ", ""))


def mark_boundaries(question: Column, sql: Column, clauses: list[str]) -> Column:
    """Clauses of the query with numbered marks, and the question's words with the mark of the first clause that has them."""
    parts = F.split(sql, rf"(?i)(?=\b(?:{'|'.join(clauses)})\b)")
    words_of = F.transform(parts, lambda p: F.split(F.lower(p), "[^a-z0-9]+"))

    def marked(word: Column) -> Column:
        plain = F.lower(F.regexp_replace(word, "[^A-Za-z0-9]", ""))
        at = F.array_position(F.transform(words_of, lambda own: F.array_contains(own, plain)), True)
        return F.when((plain != "") & (at > 0), F.concat(F.lit("[c"), (at - 1).cast("string"), F.lit("] "), word)).otherwise(word)

    left = F.array_join(F.transform(F.split(question, " "), marked), " ")
    right = F.array_join(F.transform(parts, lambda p, i: F.concat(F.lit("[c"), i.cast("string"), F.lit("] "), p)), "")
    return F.concat_ws(" || ", left, right)


def naive_pieces(col: Column, size: int) -> Column:
    """Pieces of fixed length that ignore boundaries."""
    starts = F.sequence(F.lit(1), F.greatest(F.length(col), F.lit(1)), F.lit(size))
    return F.transform(starts, lambda i: F.substring(col, i, F.lit(size)))


def boundary_violations(df: DataFrame, name: str, size: int) -> DataFrame:
    """Pieces of fixed length that hold an underscore together with letters of a part."""
    pieces = naive_pieces(F.col(name), size)
    return df.withColumn("violations", F.size(F.filter(pieces, lambda p: p.contains("_") & (F.length(p) > 1))))


def normalise_sql(col: Column) -> Column:
    """Lower case outside quotes, single spaces, no closing semicolon."""
    parts = F.split(col, "'")
    cased = F.array_join(F.transform(parts, lambda p, i: F.when(i % 2 == 0, F.lower(F.regexp_replace(p, r"\s+", " "))).otherwise(p)), "'")
    return F.trim(F.regexp_replace(cased, r"\s*;\s*$", ""))
