"""Session settings, and what a job needs to know of the session it is given."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

# Settings that plans here are written for; all but the master can be changed on a running session.
SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.locality.wait": "0",
}


def local_session(cores: int | str = "*", shuffle: int = 8, memory: str = "8g") -> SparkSession:
    """A local session for tests and the bench."""
    builder = SparkSession.builder.master(f"local[{cores}]").appName("tricount").config("spark.sql.shuffle.partitions", str(shuffle)).config("spark.driver.memory", memory)
    for k, v in SETTINGS.items():
        builder = builder.config(k, v)
    spark = builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def remove(spark: SparkSession, paths: list[str]) -> None:
    """Delete folders of stored tables that nothing needs any more."""
    context = spark.sparkContext
    for path in paths:
        p = context._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(context._jsc.hadoopConfiguration()).delete(p, True)
    paths.clear()


_FOLDERS: set[str] = set()


def shared_folder(spark: SparkSession) -> str:
    """This application's folder below spark.checkpoint.dir, which goes when the application ends.

    Only a local session may lack that setting: it gets a folder of its own. On a cluster other machines could not read one.
    """
    context = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        kept = context._jsc.sc().getCheckpointDir()
        if kept.isEmpty():
            if not context.master.startswith("local"):
                raise RuntimeError("spark.checkpoint.dir has to name a folder that driver and executors share")
            context.setCheckpointDir(tempfile.mkdtemp(prefix="tricount-"))
            kept = context._jsc.sc().getCheckpointDir()
        folder = kept.get()
    path = f"{folder.rstrip('/')}/tricount-{context.applicationId}"
    if path not in _FOLDERS:
        _FOLDERS.add(path)

        def clean() -> None:
            with contextlib.suppress(Exception):  # the session may be gone
                remove(spark, [path])

        atexit.register(clean)
    return path


#: Has Spark remove the files of a query's shuffles as soon as it has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, records: int = 0) -> tuple[DataFrame, str]:
    """``df`` written to the shared folder and read again, and its path there. The shuffles behind it go at once. records: rows of a file at most, if any."""
    path = f"{shared_folder(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    conf = df.sparkSession.conf
    before = conf.get(CLEANUP, None)
    conf.set(CLEANUP, "true")
    try:
        df.write.option("maxRecordsPerFile", records).parquet(path)
    finally:
        conf.unset(CLEANUP) if before is None else conf.set(CLEANUP, before)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


@contextlib.contextmanager
def many_tasks(spark: SparkSession, each: int = 4) -> Iterator[None]:
    """Scans of small files whose rows take long are planned as ``each`` tasks for a core, about."""
    name = "spark.sql.files.minPartitionNum"
    before = spark.conf.get(name, None)
    spark.conf.set(name, str(each * spark.sparkContext.defaultParallelism))
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def cut(df: DataFrame) -> DataFrame:
    """``df`` stored: cuts lineage, survives the loss of executors."""
    return stored(df)[0]
