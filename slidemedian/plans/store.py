"""Tables written between jobs, in a folder that driver and executors share.

The folder is the one that the session names in ``spark.checkpoint.dir``, or
else the warehouse. A lost executor costs a re-read of these files and not a
recomputation. They are removed when the session's JVM ends; ``forget`` removes
them before.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    return (named or spark.conf.get("spark.sql.warehouse.dir")).rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new path in a folder of its own, for files of this session."""
    path = f"{shared_root(spark)}/slidemedian-{label}-{uuid.uuid4().hex}"
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    # Only folders that exist can be marked.
    files.mkdirs(folder)
    files.deleteOnExit(folder)
    return f"{path}/data"


def settle(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once and read it back: a cut in the lineage."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession, *tables: DataFrame) -> None:
    """Remove the files of settled tables that no later plan reads."""
    for table in tables:
        for file in table.inputFiles()[:1]:
            folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(file).getParent()
            folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)
