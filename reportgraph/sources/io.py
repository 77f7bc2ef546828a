"""Reading the given tables and cutting lineage in the folder the cluster shares."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, ltz: bool = False) -> DataFrame:
    """Table ``name`` of a data folder; ``ltz`` casts zone-less timestamps to TIMESTAMP (needed for watermarks)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if ltz:
        df = df.withColumns({c: F.col(c).cast("timestamp") for c, t in df.dtypes if t == "timestamp_ntz"})
    return df


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, which driver and executors share.

    Only where neither the setting nor a checkpoint folder exists one is made, and only for a local master (as in tests); on a
    cluster that is an error, since executors would not share it.
    """
    sc = spark.sparkContext
    given = spark.conf.get("spark.checkpoint.dir", None)
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not given and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set, so driver and executors share no folder")
        sc.setCheckpointDir(given or f"/tmp/checkpoints/{sc.applicationId}")
    return given or sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` written to the shared checkpoint folder and read from there."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder as columns and read from there: for tables of many rows, of which a later step reads the columns it needs."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def tasks(spark: SparkSession) -> int:
    """How many tasks a table is dealt to whose rows take far more work than room: a few for each core, since each task writes a file for each one of the next step."""
    cores = spark.sparkContext.defaultParallelism
    return max(cores, min(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * cores))
