"""Tables written between the rounds of an iterative plan.

A round's result goes to the shared folder that the session names in
``spark.checkpoint.dir`` and is read again, so a lost executor costs a re-read and not
the whole lineage. Only where that setting is absent, in local mode (tests), a temporary folder is
used; a cluster without a shared folder is an error.
"""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder of the session; one is set if the session has none."""
    context = spark.sparkContext
    folder = context.getCheckpointDir()
    if folder is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="graphparts-"))
        folder = context.getCheckpointDir()
    return folder


def written(df: DataFrame, label: str = "table") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and return what was written."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dropped(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete tables made by :func:`written` once nothing reads them any more."""
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for table in tables:
        for folder in {f.rsplit("/", 1)[0] for f in table.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(conf).delete(path, True)


_LOCK = threading.Lock()
#: For each session how many plans run within :func:`small_batches`, and the setting before the first of them.
_WITHIN: dict[int, tuple[int, str | None]] = {}


@contextmanager
def small_batches(spark: SparkSession, size: str = "8m") -> Iterator[None]:
    """Groups of large rows go to Python in batches of about ``size``, so that the JVM never holds a second copy of a group; for plans that run within, also of several threads."""
    name, key = "spark.sql.execution.arrow.maxBytesPerBatch", id(spark)
    with _LOCK:
        count, before = _WITHIN.get(key, (0, None))
        if not count:
            before = spark.conf.get(name, None)
            spark.conf.set(name, size)
        _WITHIN[key] = (count + 1, before)
    try:
        yield
    finally:
        with _LOCK:
            count, before = _WITHIN.pop(key)
            if count > 1:
                _WITHIN[key] = (count - 1, before)
            elif before is None:
                spark.conf.unset(name)
            else:
                spark.conf.set(name, before)
