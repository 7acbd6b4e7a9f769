"""Bounded samples of labelled rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def least_hashed(df: DataFrame, keys: list[str], most: int) -> DataFrame:
    """At most ``most`` distinct rows of ``keys``: those that hash lowest, so copies of a row take one place together.

    A first pass estimates the number of distinct rows and sets a ceiling under which about twice as many as wanted fall: only
    those are made distinct and sent on, whatever the size of the table, and the chosen ones are the same as without it.
    Null keys hash like any value; an empty table gives no rows.
    """
    h = F.xxhash64(*keys)
    distinct = df.agg(F.approx_count_distinct(h)).first()[0]  # within some per cent
    share = min(1.0, (2 * most + 1000) / max(1, distinct))
    ceiling = min(2**63 - 1, int(-(2**63) + share * 2**64))
    return df.where(h <= F.lit(ceiling)).select(*keys).distinct().orderBy(h, *keys).limit(most)
