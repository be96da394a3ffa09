"""Tables that cut lineage, in the folder that the cluster names in ``spark.checkpoint.dir``.

They are Parquet files all executors share, so they outlive any executor.  Only where the
setting is absent (tests) a temporary folder is made.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="thinfsm-")
        spark.conf.set("spark.checkpoint.dir", root)
    return root.rstrip("/")


def store(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: lineage ends there."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/thinfsm/{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._thinfsm_path = path
    return out


def drop(df: DataFrame) -> None:
    """Delete a table made by store() that nothing reads any more."""
    path = getattr(df, "_thinfsm_path", None)
    if path:
        jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(conf).delete(p, True)
