"""Tables in the folder that driver and executors share: they cut lineage and survive lost executors.

All tables of an application lie in one folder of its own there, which goes when the application ends.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, of the context or of the session; a local one only where neither names any, as in tests."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        import tempfile

        root = f"file://{tempfile.gettempdir()}/embedvocab-shared"
    return root.rstrip("/")


def new_path(spark: SparkSession) -> str:
    """A path of its own in the application's folder."""
    context = spark.sparkContext
    folder = f"{shared_folder(spark)}/embedvocab-{context.applicationId}"
    if getattr(context, "_embedvocab_folder", None) != folder:
        path = context._jvm.org.apache.hadoop.fs.Path(folder)
        files = path.getFileSystem(context._jsc.hadoopConfiguration())
        files.mkdirs(path)  # only what exists can be marked
        files.deleteOnExit(path)
        context._embedvocab_folder = folder
    return f"{folder}/{uuid.uuid4().hex}"


#: Rows of a stored table that a join broadcasts; beyond it both sides are shuffled.
SMALL = 1 << 18


def small(table: DataFrame) -> DataFrame:
    """A stored table, to be broadcast if it is counted to be small, so that what it is joined with stays where it is."""
    return F.broadcast(table) if table.count() <= SMALL else table


def stored(df: DataFrame) -> DataFrame:
    """df, written once and read from there."""
    path = new_path(df.sparkSession)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
