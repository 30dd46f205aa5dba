"""Normalization of blocking values, and a hash that Spark and SQL engines agree on."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def ascii_fold(c: Column | str) -> Column:
    """Lower case; every run of what isn't a-z becomes one space; trimmed.  Null stays null."""
    return F.trim(F.regexp_replace(F.lower(_col(c)), "[^a-z]+", " "))


def hash8(*parts: Column | str) -> Column:
    """The first 8 hex digits of the md5 of the parts joined by ``|``, as a long."""
    joined = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("long")
