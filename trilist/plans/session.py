"""Session settings and the cut of lineage that loops need."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Runtime settings for large graphs; none of them is fixed at session start.
SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.optimizer.runtime.bloomFilter.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
}


def configure(spark: SparkSession, input_bytes: int | None = None) -> SparkSession:
    """Apply SETTINGS, and shuffle partitions of about 128 MB where the input size is given."""
    for key, value in SETTINGS.items():
        spark.conf.set(key, value)
    if input_bytes:
        spark.conf.set("spark.sql.shuffle.partitions", str(max(8, input_bytes >> 27)))
    return spark


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which all executors share. Where it is unset: on a local master (as in tests) a temporary one, elsewhere an error."""
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        if not sc.master.split("[")[0] == "local":
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="trilist-shared-")
        sc.setCheckpointDir(found)
    return found.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint to the shared folder."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def store(df: DataFrame) -> DataFrame:
    """The same for tables of many rows that are read often: as columns in a file, a fraction of a checkpoint's bytes."""
    path = f"{shared_folder(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
