"""Tables between steps: written once in shared storage and read again."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_roots: dict[str, str] = {}


def scratch_root(spark: SparkSession) -> str:
    """A folder of this session below ``spark.checkpoint.dir``. Where that is unset, a temporary one if
    driver and executors are one process; on a cluster it must be set, since they share no local folder."""
    context = spark.sparkContext
    base = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not base:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="embedmine-")
        context.setCheckpointDir(base)
    key = f"{context.applicationId}:{base}"
    if key not in _roots:
        _roots[key] = f"{base.rstrip('/')}/embedmine-{uuid.uuid4().hex}"
        atexit.register(_remove, spark, _roots[key])
    return _roots[key]


def _remove(spark: SparkSession, path: str) -> None:
    try:
        place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    except Exception:  # the session has gone already; the folder is scratch
        pass


def written(df: DataFrame, name: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """One step's table: cuts the lineage, survives lost executors, spills to disk by nature."""
    path = f"{scratch_root(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.partitionBy(*partition_by) if partition_by else df.write
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """The rows dealt evenly to as many tasks as a shuffle has, before a step that multiplies them without
    another shuffle: few small files, or few partitions merged by their size, would leave most cores idle."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)
