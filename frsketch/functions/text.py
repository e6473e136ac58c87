"""Texts as sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def words(text: Column) -> Column:
    return F.split(F.trim(F.lower(text)), r"\s+")


def word_shingles(df: DataFrame, key: str, text: str | Column, size: int = 3) -> DataFrame:
    """(key, shingle) rows; texts below ``size`` words have none."""
    rows = df.select(key, words(F.col(text) if isinstance(text, str) else text).alias("w")).where(F.size("w") >= size)
    each = F.transform(F.sequence(F.lit(1), F.size("w") - (size - 1)), lambda i: F.array_join(F.slice("w", i, size), " "))
    return rows.select(key, F.explode(each).alias("shingle"))


def char_shingles(df: DataFrame, key: str, text: str, size: int = 5) -> DataFrame:
    rows = df.select(key, F.lower(text).alias("t")).where(F.length("t") >= size)
    each = F.transform(F.sequence(F.lit(1), F.length("t") - (size - 1)), lambda i: F.substr(F.col("t"), i, F.lit(size)))
    return rows.select(key, F.explode(each).alias("shingle"))


def strip_html(html: Column) -> Column:
    """Text without scripts, styles, comments and tags."""
    bare = F.regexp_replace(html, r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")
    return F.regexp_replace(bare, r"(?s)<[^>]*>", " ")
