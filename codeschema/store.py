"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


_paths: dict[str, list[str]] = {}
#: Files of more bytes than this may hold more rows than a broadcast can carry: rows of programs repeat, and shrink a hundredfold and more.
MOST_BROADCAST = 64 << 10


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``.  A folder of our own is made only where driver and executors are one process and the session
    names none; on a cluster that is an error, as executors could not read it."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir has to name a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="codeschema-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def written(df: DataFrame, label: str) -> DataFrame:
    """``df`` written out and read back: computed once, and its lineage ends there.  ``release`` removes what was written.

    Spark takes the files' size for the rows' and would gather millions of rows in the driver to broadcast them, so joins of
    all but the smallest are merge joins.
    """
    spark, path = df.sparkSession, f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    _paths.setdefault(spark.sparkContext.applicationId, []).append(path)
    back = spark.read.schema(df.schema).parquet(path)
    return back if int(str(back._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) <= MOST_BROADCAST else back.hint("merge")


def release(spark: SparkSession) -> int:
    """Removes all that ``written`` has left in the shared folder for this application; nothing made from it may be used after."""
    paths = _paths.pop(spark.sparkContext.applicationId, [])
    jvm = spark.sparkContext._jvm
    for p in paths:
        target = jvm.org.apache.hadoop.fs.Path(p)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    return len(paths)
