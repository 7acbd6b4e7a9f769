"""Intermediate tables in the folder that the cluster shares.

``spark.checkpoint.dir`` names that folder. Lineage is cut by writing Parquet there and reading it
back: the files are compressed, survive lost executors, and give the next plan exact statistics.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """URI of the shared scratch folder.

    Without ``spark.checkpoint.dir`` a temporary folder serves, but only where driver and executors
    are one process (``local[...]``); on a cluster the setting is required.
    """
    named = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        made = tempfile.mkdtemp(prefix="dpgrid_")
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        _LOCAL[app] = "file://" + made
    return _LOCAL[app]


def new_path(spark: SparkSession, label: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_dir(spark)}/{label}_{uuid.uuid4().hex}"


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once and return the table read back: a checkpoint in columnar form."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_tables(spark: SparkSession, *frames: DataFrame) -> None:
    """Delete the files of materialised frames that no later plan reads."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for df in frames:
        for uri in {os.path.dirname(f) for f in df.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(uri)
            path.getFileSystem(conf).delete(path, True)
