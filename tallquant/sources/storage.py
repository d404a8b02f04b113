"""Sinks and sources around the engine: formats, partitioned and bucketed tables, saved fits."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from tallquant.operators.conditioning import Conditioner


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder (``spark.checkpoint.dir``), which goes when the application ends.

    Where the folder is unset, a local master gets a temporary one; on a cluster,
    whose executors could not see that, it is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="tallquant_")
        spark.sparkContext.setCheckpointDir(root)
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    folder = jvm.org.apache.hadoop.fs.Path(f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex[:10]}")
    fs = folder.getFileSystem(conf)
    fs.mkdirs(folder)
    fs.deleteOnExit(folder)
    return f"{folder.toString()}/data"


def kept(design: DataFrame) -> DataFrame:
    """A design that several passes read, as Parquet in the shared folder: indicators pack to bits there, while cached rows take eight octets for each cell."""
    path = scratch(design.sparkSession, "design")
    design.write.parquet(path)
    return design.sparkSession.read.schema(design.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a folder that no later step reads."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def save_conditioner(spark: SparkSession, c: Conditioner, path: str) -> None:
    """One row for each entry (i, j) of R and its inverse."""
    spark.createDataFrame(c.rows(), "method string, i int, j int, r double, rinv double, kappa_bound double").write.mode("overwrite").parquet(path)


def load_conditioner(spark: SparkSession, path: str) -> Conditioner:
    import numpy as np

    rows = spark.read.parquet(path).collect()
    d = max(r.i for r in rows) + 1
    r, rinv = np.zeros((d, d)), np.zeros((d, d))
    for row in rows:
        r[row.i, row.j], rinv[row.i, row.j] = row.r, row.rinv
    return Conditioner(rows[0].method, r, rinv, 0, 0.0, rows[0].kappa_bound)


def save_fits(fits: DataFrame, path: str) -> None:
    fits.write.mode("append").parquet(path)


def load_fits(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """Write and read again in a text or columnar format, with the schema given."""
    path = scratch(df.sparkSession, fmt)
    writer = df.write.option("header", True) if fmt == "csv" else df.write
    writer.format(fmt).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def write_partitioned(df: DataFrame, by: str, name: str) -> str:
    """Hash-deal by the partition column first, so each value is written by one task and small files stay few."""
    path = scratch(df.sparkSession, name)
    df.repartition(by).write.partitionBy(by).parquet(path)
    return path


def write_bucketed(df: DataFrame, by: str, table: str, buckets: int = 8) -> DataFrame:
    """A bucketed table in a fresh path of the shared folder: later joins on the key need no exchange."""
    name = f"{table}_{uuid.uuid4().hex[:8]}"
    df.write.bucketBy(buckets, by).sortBy(by).option("path", scratch(df.sparkSession, name)).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)
