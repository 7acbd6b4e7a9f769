"""Registry of the library's queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from dpgrid import catalog
from dpgrid import experiments as _experiments  # registers its queries


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells and clusters of the trimmed release on the three-spiral view."""
    return catalog.QUERIES["trim_w2"](spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(catalog.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(catalog.ORACLES)
