"""Lineage cuts that survive lost executors.

Iterative operators cut their lineage with reliable checkpoints, or with Parquet tables below the
checkpoint folder when a table is read more than once. The folder comes from ``spark.checkpoint.dir``;
only a session without one gets a folder of its own (a temporary one when the master is local, one
below the warehouse otherwise).
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder for checkpoints, set on the context if nothing has set it."""
    given = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    current = spark.sparkContext.getCheckpointDir()
    if given:
        if current is None:
            spark.sparkContext.setCheckpointDir(given)
        return given
    if current is None:
        if spark.sparkContext.master.startswith("local"):
            current = tempfile.mkdtemp(prefix="concord-")
        else:
            current = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
        spark.sparkContext.setCheckpointDir(current)
    return current


def cut(df: DataFrame) -> DataFrame:
    """A reliable, eager checkpoint."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def keep(df: DataFrame) -> DataFrame:
    """Write a table once below the shared folder and return a scan of it (columnar, prunable, re-readable)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


#: Bytes of a value beyond which a hundred rows are much to hold; the largest dictionary that is asked for.
WIDE, DICTIONARY = 100_000, 64_000_000


def wide_rows(spark: SparkSession, size: int) -> None:
    """Fits Parquet writers of the session to values of up to so many bytes, where nobody has set them.

    By default a writer looks at its memory every hundred rows, and a dictionary holds a megabyte, so equal texts of more are written out each time. It looks at every second row
    then: it gives a dictionary up for good where that saves nothing in the first page, and one row saves nothing.
    """
    if size > WIDE:
        for key, value in (("parquet.page.size.row.check.min", 2), ("parquet.dictionary.page.size", max(1 << 20, min(DICTIONARY, size + (1 << 16))))):
            if spark.conf.get(key, None) is None and spark.sparkContext._jsc.hadoopConfiguration().get(key) is None:
                spark.conf.set(key, str(value))
