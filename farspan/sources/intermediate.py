"""Cutting lineage with tables in the folder that all executors share."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession

#: Where tables go if no checkpoint folder is set and the session runs on one machine, as in tests.
LOCAL_DIR = "/tmp/checkpoints"
BATCH_BYTES = 4 << 20
_ARROW_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_made: ContextVar[list[str] | None] = ContextVar("made", default=None)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a folder of our own only on a single machine without one."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = LOCAL_DIR
    return found.rstrip("/")


def written(df: DataFrame, label: str) -> DataFrame:
    """df as a table in the shared folder: its lineage ends there, and lost executors cost no recomputation.

    The shuffle files that it was made from go when it is written, as nothing reads them again.
    """
    spark = df.sparkSession
    path, schema = f"{shared_dir(spark)}/farspan-{label}-{uuid.uuid4().hex}", df.schema
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)
    if (made := _made.get()) is not None:
        made.append(path)
    return spark.read.schema(schema).parquet(path)


def adopt(path: str) -> None:
    """Leave a table that an inner ``scratch`` let go to the outer one, if there is one."""
    if (made := _made.get()) is not None:
        made.append(path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[list[str]]:
    """Tables written inside are deleted at the end: save results before leaving. Other tables stay."""
    made: list[str] = []
    token = _made.set(made)
    try:
        yield made
    finally:
        _made.reset(token)
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        for name in made:
            path = jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(conf).delete(path, True)


def lean_batches(df: DataFrame) -> DataFrame:
    """df, in a session that ships rows to Python in batches of 4 MB at most: texts and windows are wide, and the buffers
    of both sides grow with a batch.  The setting stays with the session; one that is smaller already is kept."""
    conf = df.sparkSession.conf
    held = str(conf.get(_ARROW_BYTES, "64m")).lower().rstrip("b")
    size = int(held[:-1]) << {"k": 10, "m": 20, "g": 30}[held[-1]] if held[-1:] in ("k", "m", "g") else int(held)
    if size > BATCH_BYTES:
        conf.set(_ARROW_BYTES, str(BATCH_BYTES))
    return df
