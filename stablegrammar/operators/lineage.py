"""Cutting lineage with files that every executor can read."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """A folder of this session in spark.checkpoint.dir. Only a local master, which has no other machine, may do without that setting."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        where = spark.conf.get("spark.checkpoint.dir", "") or sc.getConf().get("spark.checkpoint.dir", "")
        if not where and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        if not where:
            where = tempfile.mkdtemp(prefix="checkpoints-")
            atexit.register(shutil.rmtree, where, ignore_errors=True)
        sc.setCheckpointDir(where)
    return sc.getCheckpointDir()


#: The setting by which Spark drops a query's shuffle files at its end.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settled(df: DataFrame, once: bool = False) -> DataFrame:
    """The same rows, read back from a Parquet table in the shared folder.

    Its readers take only the columns they need, and the planner learns its true size: size estimates of checkpoints are products over
    the joins before them, which a loop that joins its own results would square at each turn. With `once`, nothing else will want the
    plan's shuffles, and their files go when the rows are written.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, None)
    if once:
        spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        if once:
            spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


checkpointed = settled
