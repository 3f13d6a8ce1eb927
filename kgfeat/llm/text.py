"""Word splitting and column names shared by the operators: words are runs of anything but blank and tab to carriage return."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = " \t\n\x0b\x0c\r"
BROADCAST_KEYS = 200_000  # rows of a key and a number or two


def word_count(text: Column) -> Column:
    """Number of words; null counts none."""
    t = F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANKS))
    return F.when(t == "", F.lit(0)).otherwise(F.size(F.split(t, r"[\x20\x09-\x0D]+", -1))).cast("long")


def words_of(text: str | None) -> list[bytes]:
    """The same words as UTF-8; bytes.split() cuts at exactly these six characters."""
    return text.encode("utf-8", "surrogatepass").split() if text else []


def key_of(col: Column) -> Column:
    """A string key in which null is a value of its own, sorted last."""
    return F.when(col.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), col.cast("string")))


def neutral(docs: DataFrame, *wanted: str) -> tuple[DataFrame, list[str]]:
    """docs with its columns named c0, c1, ... so that no column of ours can clash with one of theirs,
    and the new names of the wanted columns. ``given_back`` undoes it."""
    at = {c: k for k, c in reversed(list(enumerate(docs.columns)))}
    low = {c.casefold(): k for c, k in at.items()}
    return docs.toDF(*(f"c{k}" for k in range(len(docs.columns)))), [f"c{at.get(w, low.get(w.casefold()))}" for w in wanted]


def given_back(rows: DataFrame, docs: DataFrame, *more: Column) -> DataFrame:
    """The columns of docs under their own names, and more."""
    return rows.select(*(F.col(f"c{k}").alias(c) for k, c in enumerate(docs.columns)), *more)


def sent_if_few(rows: DataFrame, most: int = BROADCAST_KEYS) -> DataFrame:
    """A saved table of keys, to be sent to the texts that it is joined with while it is counted to be short;
    a longer one is left to a shuffle of both sides."""
    return F.broadcast(rows) if rows.count() <= most else rows


def row_key(ident: str, text: str) -> Column:
    """A key that tells rows of one id apart by their text, ordered by id with null last."""
    return F.struct(F.col(ident).isNull().alias("none"), F.col(ident).alias("i"), F.xxhash64(text).alias("h"))
