"""Workload views: points placed by fixed formulas on the given tables.

Each view is one SELECT, written once for Spark and for DuckDB; the few words in which the engines differ are filled in. All constants
are doubles. Columns: ``point_id, x0, x1`` (``x2``), ``truth``.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from dpgrid.operators.grid import GridSpec, unit

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings")


def hex_int(text: str, digits: int, engine: str) -> str:
    """SQL of the integer that the first digits of a text's MD5 spell."""
    part = f"substr(md5({text}), 1, {digits})"
    return f"CAST(conv({part}, 16, 10) AS BIGINT)" if engine == "spark" else f"CAST('0x' || {part} AS BIGINT)"


#: Elements that the random projection of embeddings reads; lacking ones count as zero.
PROJECTED = 64


def element(i: int, engine: str) -> str:
    """SQL of an embedding's element, null beyond its end."""
    return f"try_element_at(embedding, {i})" if engine == "spark" else f"embedding[{i}]"


def projection(axis: int, engine: str) -> str:
    """SQL of a fixed random projection: signs by the MD5 of axis and place, scaled so that unit vectors keep the spread of one element."""
    signs = ["+" if hashlib.md5(f"projection|{axis}|{i}".encode()).digest()[0] < 128 else "-" for i in range(1, PROJECTED + 1)]
    total = " ".join(f"{sign} coalesce(CAST({element(i, engine)} AS DOUBLE), 0e0)" for i, sign in enumerate(signs, 1))
    return f"((0e0 {total}) / {PROJECTED**0.5!r}e0)"


_LINE_ID = "concat_ws('|', CAST(l_orderkey AS STRING), CAST(l_partkey AS STRING), CAST(l_suppkey AS STRING), CAST(l_linenumber AS STRING), CAST(CAST(round(l_extendedprice * 100e0) AS BIGINT) AS STRING))"
_T = "((l_extendedprice - 900e0) / 104100e0)"
_J = "((l_quantity - 1e0 + 100e0 * l_discount / 11e0) / 50e0)"

_GAUSS = """
SELECT o_orderkey AS point_id, (i + 0.5e0) / 5e0 + 0.027e0 * r * cos(2e0 * pi() * u) AS x0, (s + 0.5e0) / 3e0 + 0.045e0 * r * sin(2e0 * pi() * u) AS x1, CAST(3 * i + s AS INT) AS truth
FROM (SELECT o_orderkey, CAST(substr(o_orderpriority, 1, 1) AS INT) - 1 AS i, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS s,
  sqrt(-2e0 * ln((o_totalprice - 999e0) / 499001e0)) AS r, (o_custkey * 0.6180339887498949e0) % 1e0 AS u FROM {orders}) q
"""
_SPIRAL = """
SELECT {line_id} AS point_id, 0.5e0 + r * cos(a) AS x0, 0.5e0 + r * sin(a) AS x1, arm AS truth
FROM (SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, arm, 2e0 * pi() * arm / 3e0 + 4.2e0 * t AS a, 0.10e0 + 0.36e0 * t + 0.022e0 * (j - 0.5e0) AS r
  FROM (SELECT *, {t} AS t, {j} AS j, CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS arm FROM {lineitem}) q) p
"""
_MIXED = """
SELECT {line_id} AS point_id,
  CASE p_type WHEN 'ECONOMY' THEN 0.27e0 + 0.20e0 * (1e0 + 0.25e0 * (j - 0.5e0)) * cos(2e0 * pi() * t)
    WHEN 'PROMO' THEN 0.27e0 + 0.05e0 * sqrt(j) * cos(2e0 * pi() * t)
    WHEN 'MEDIUM' THEN 0.76e0 + 0.17e0 * (1e0 + 0.25e0 * (j - 0.5e0)) * cos(pi() * t)
    WHEN 'SMALL' THEN CASE WHEN t < 0.45e0 THEN 0.12e0 + 0.08e0 * sqrt(j) * cos(2e0 * pi() * t / 0.45e0) WHEN t < 0.9e0 THEN 0.40e0 + 0.08e0 * sqrt(j) * cos(2e0 * pi() * (t - 0.45e0) / 0.45e0) ELSE 0.12e0 + 0.28e0 * (t - 0.9e0) / 0.1e0 END
    ELSE CASE WHEN t < 0.45e0 THEN 0.66e0 + 0.07e0 * sqrt(j) * cos(2e0 * pi() * t / 0.45e0) WHEN t < 0.9e0 THEN 0.90e0 + 0.07e0 * sqrt(j) * cos(2e0 * pi() * (t - 0.45e0) / 0.45e0) ELSE 0.66e0 + 0.24e0 * (t - 0.9e0) / 0.1e0 END END AS x0,
  CASE p_type WHEN 'ECONOMY' THEN 0.73e0 + 0.20e0 * (1e0 + 0.25e0 * (j - 0.5e0)) * sin(2e0 * pi() * t)
    WHEN 'PROMO' THEN 0.73e0 + 0.05e0 * sqrt(j) * sin(2e0 * pi() * t)
    WHEN 'MEDIUM' THEN 0.62e0 + 0.25e0 * (1e0 + 0.25e0 * (j - 0.5e0)) * sin(pi() * t)
    WHEN 'SMALL' THEN CASE WHEN t < 0.45e0 THEN 0.25e0 + 0.10e0 * sqrt(j) * sin(2e0 * pi() * t / 0.45e0) WHEN t < 0.9e0 THEN 0.25e0 + 0.10e0 * sqrt(j) * sin(2e0 * pi() * (t - 0.45e0) / 0.45e0) ELSE 0.25e0 + 0.03e0 * (j - 0.5e0) END
    ELSE CASE WHEN t < 0.45e0 THEN 0.25e0 + 0.12e0 * sqrt(j) * sin(2e0 * pi() * t / 0.45e0) WHEN t < 0.9e0 THEN 0.25e0 + 0.12e0 * sqrt(j) * sin(2e0 * pi() * (t - 0.45e0) / 0.45e0) ELSE 0.25e0 + 0.03e0 * (j - 0.5e0) END END AS x1,
  CASE p_type WHEN 'ECONOMY' THEN 0 WHEN 'PROMO' THEN 1 WHEN 'MEDIUM' THEN 2 WHEN 'SMALL' THEN 3 ELSE 4 END AS truth
FROM (SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, p_type, {t} AS t, {j} AS j FROM {lineitem} JOIN {part} ON l_partkey = p_partkey WHERE p_type <> 'LARGE') q
"""
_CHECKIN = """
SELECT {line_id} AS point_id, cx + 0.035e0 * w * r * cos(2e0 * pi() * f) AS x0, cy + 0.05e0 * w * r * sin(2e0 * pi() * f) AS x1, n_nationkey AS truth, l_shipdate AS at
FROM (SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, l_shipdate, n_nationkey,
    0.08e0 + 0.84e0 * ((0.7548776662466927e0 * n_nationkey) % 1e0) AS cx, 0.08e0 + 0.84e0 * ((0.5698402909980532e0 * n_nationkey) % 1e0) AS cy,
    0.4e0 + 0.3e0 * n_regionkey / 4e0 AS w, sqrt(-2e0 * ln((l_extendedprice - 899e0) / 104101e0)) AS r, (0.6180339887498949e0 * l_partkey) % 1e0 AS f
  FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey
  WHERE (37 * l_partkey + 11 * l_suppkey) % 25 >= n_nationkey) q
"""
_PRICE = "SELECT {line_id} AS point_id, l_extendedprice AS x0, l_quantity AS x1, CAST(NULL AS INT) AS truth FROM {lineitem}"
_CLOCK = "SELECT event_id AS point_id, (hour(ts) * 60 + minute(ts)) / 1440e0 AS x0, ln(value + 1e0) / ln(501e0) AS x1, CAST({json_k} AS DOUBLE) / 100e0 AS x2, CAST(NULL AS INT) AS truth FROM {events}"
_EMBED = "SELECT vec_id AS point_id, CAST({e1} AS DOUBLE) AS x0, CAST({e2} AS DOUBLE) AS x1, CAST({e3} AS DOUBLE) AS x2, label AS truth, embedding FROM {embeddings}"
_PROJECT = "SELECT vec_id AS point_id, {r0} AS x0, {r1} AS x1, label AS truth FROM {embeddings} WHERE embedding IS NOT NULL"
_TEXT = """
SELECT doc_id AS point_id, ln(n_chars + 1e0) / ln(200001e0) AS x0, coalesce((length(text) - length(replace(replace(replace(replace(replace(lower(text), 'a', ''), 'e', ''), 'i', ''), 'o', ''), 'u', ''))) * 1e0 / nullif(length(text), 0), 0e0) AS x1, CAST(NULL AS INT) AS truth FROM {documents}
"""
_INCOME = """
SELECT c_custkey AS point_id, (c_acctbal + 1000e0) / 11000e0 AS x0, CAST(sum(CAST(round(o_totalprice * 100e0) AS BIGINT)) AS DOUBLE) / 100e0 / count(*) / 500000e0 AS x1, CAST(NULL AS INT) AS truth
FROM {customer} JOIN {orders} ON c_custkey = o_custkey GROUP BY c_custkey, c_acctbal
"""


@dataclass(frozen=True)
class Workload:
    name: str
    query: str
    spec: GridSpec
    p: float
    tables: tuple[str, ...]

    @property
    def cols(self) -> list[str]:
        return [f"x{a}" for a in range(self.spec.n)]

    def sql(self, engine: str) -> str:
        """The view's SELECT; for Spark the tables stay as placeholders."""
        words = {
            "line_id": hex_int(_LINE_ID, 15, engine), "t": _T, "j": _J,
            "json_k": "get_json_object(props, '$.k')" if engine == "spark" else "json_extract_string(props, '$.k')",
            **{f"e{i}": element(i, engine) for i in (1, 2, 3)}, **{f"r{a}": projection(a, engine) for a in (0, 1)},
        }
        made = self.query
        for k, v in words.items():
            made = made.replace("{" + k + "}", v)
        if engine != "spark":
            for t in TABLES:
                made = made.replace("{" + t + "}", t)
            made = made.replace("AS STRING)", "AS VARCHAR)")
        return made.strip()

    def points(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """The view over a folder of tables; only the columns it names are read."""
        return spark.sql(self.sql("spark"), **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in self.tables})


def _w(name: str, query: str, spec: GridSpec, p: float, *tables: str) -> Workload:
    return Workload(name, query, spec, p, tables)


_CUBE3 = GridSpec((-0.5,) * 3, (0.5,) * 3, (16,) * 3)
#: The grid and percentile of each view.
WORKLOADS: dict[str, Workload] = {
    "w1": _w("gauss15", _GAUSS, unit(64), 0.58, "orders"),
    "w2": _w("spiral3", _SPIRAL, unit(40), 0.10, "lineitem"),
    "w3": _w("mixed5", _MIXED, unit(36), 0.23, "lineitem", "part"),
    "w4": _w("checkin", _CHECKIN, unit(80), 0.31, "lineitem", "orders", "customer", "nation"),
    "w5": _w("price_qty", _PRICE, GridSpec((900.0, 1.0), (105000.0, 50.0), (40, 40)), 0.10, "lineitem"),
    "w6": _w("event_clock", _CLOCK, unit(32), 0.25, "events"),
    "w7": _w("embed2", _EMBED, GridSpec((-0.5,) * 2, (0.5,) * 2, (16,) * 2), 0.25, "embeddings"),
    "w7_3d": _w("embed3", _EMBED, _CUBE3, 0.25, "embeddings"),
    "w7_proj": _w("embed_projected", _PROJECT, GridSpec((-0.5,) * 2, (0.5,) * 2, (16,) * 2), 0.25, "embeddings"),
    "w8": _w("text_shape", _TEXT, unit(32), 0.30, "documents"),
    "w9": _w("income_expense", _INCOME, unit(20), 0.20, "customer", "orders"),
}


def points_from(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """Points from CSV, JSON, ORC or Parquet with a declared schema; nothing is inferred from private rows."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write_release(cells: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = ()) -> None:
    """Write releasable cells; refuses columns that only the owner may see."""
    private = {"cnt", "n_pos", "n_nonpos", "k_clean", "d_clean"} & set(cells.columns)
    if private:
        raise ValueError(f"not releasable: {sorted(private)}")
    cells.write.mode("overwrite").format(fmt).partitionBy(*partition_by).save(path)
