"""Session helpers: shared folders, lineage cuts and scoped settings.

Every intermediate that must outlive its producing stage is written to the folder that
``spark.checkpoint.dir`` names, which all executors of a cluster share.  Only when that setting is
absent on a local master (unit tests) a folder of our own is created.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder shared by driver and executors; sets a checkpoint folder if the session has none."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if not folder:
        folder = context.getCheckpointDir()
    if not folder:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="redgraph-")
        context.setCheckpointDir(folder)
    elif not context.getCheckpointDir():
        context.setCheckpointDir(folder)
    return folder.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the result survives the loss of executors and has no lineage."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_placed(df: DataFrame, parts: int) -> DataFrame:
    """A reliable checkpoint that keeps how ``df`` is partitioned, so later joins on that key need no exchange.

    Adaptive plans do not tell their partitioning before they have run, so this job is planned without,
    and for as many tasks as there are owners, so that no side is dealt anew for parallelism.
    """
    shared_dir(df.sparkSession)
    with scoped(df.sparkSession, fixed(parts)):
        return df.checkpoint(eager=True)


def fixed(parts: int) -> dict[str, str]:
    """Settings under which a round over ``parts`` owners is planned."""
    return {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts)}


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet below the shared folder and read it again (columnar, prunable)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with scoped(spark, {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stage_path = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what ``staged`` wrote, once nothing reads it any more."""
    spark = df.sparkSession
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df._stage_path)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def told(watch: Observation) -> dict:
    """Observed values of a finished job; none if Spark learned that the rows are empty and dropped that part.

    A caller that gets none counts what the job wrote: a lost counter is never taken for the end of a loop.
    """
    try:
        return {k: v or 0 for k, v in dict(watch.get).items()}
    except Exception as e:  # noqa: BLE001  the gateway knows no narrower class for a dropped part
        if "java.lang.AssertionError" in str(e):
            return {}
        raise


@contextlib.contextmanager
def scoped(spark: SparkSession, settings: dict[str, str]) -> Iterator[None]:
    """Set runtime settings for a block and restore what was there before."""
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def task_count(spark: SparkSession) -> int:
    """Shuffle partitions of the session, the unit in which data-sized exchanges are dealt."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
