"""Blacklists: exact URIs, or prefixes where an entry ends in ``*``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def matches(uri: Column, entries: tuple[str, ...]) -> Column:
    """True where uri is one of the entries or begins with one of the prefixes; never null."""
    exact = [e for e in entries if not e.endswith("*")]
    out = uri.isin(exact) if exact else F.lit(False)
    for e in entries:
        if e.endswith("*"):
            out = out | uri.startswith(e[:-1])
    return F.coalesce(out, F.lit(False))


def match(vocab: DataFrame, entries: tuple[str, ...], uri_col: str = "uri") -> DataFrame:
    """The rows of a vocabulary that are blacklisted."""
    return vocab.filter(matches(F.col(uri_col), entries))
