"""Tables written to the shared folder and read back, to end the lineage of iterative methods; files that appear at once."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, local mode takes an own one."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.kmerspark.local.dir", None)
    if where:
        return where
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    where = tempfile.mkdtemp(prefix="kmerspark-")
    spark.conf.set("spark.kmerspark.local.dir", where)
    return where


#: What this process has written to the shared folder and not yet cleared.
WRITTEN: list[str] = []


def clear_stored(spark: SparkSession) -> None:
    """Delete the intermediate tables of this process. Results that are still to be read must not rest on them."""
    for path in WRITTEN:
        _delete(spark, path)
    WRITTEN.clear()


def shared_path(spark: SparkSession) -> str:
    """A new path in the shared folder."""
    WRITTEN.append(f"{shared_dir(spark)}/kmerspark-{uuid.uuid4().hex}")
    return WRITTEN[-1]


#: The engine's switch by which an execution deletes its shuffles' files when it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_released(spark: SparkSession) -> Iterator[None]:
    """Writes within leave no shuffle files. Else those stay until the driver happens to collect its garbage."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


@contextmanager
def passing(spark: SparkSession) -> Iterator[list[DataFrame]]:
    """What is written to the shared folder within is deleted at the end, shuffle files too; nothing later may rest on it.

    Stored tables that are put on the list stay.
    """
    before, kept = set(WRITTEN), []
    try:
        with shuffles_released(spark):
            yield kept
    finally:
        before |= {t._stored_at for t in kept}
        for path in [p for p in WRITTEN if p not in before]:
            WRITTEN.remove(path)
            _delete(spark, path)


def stored(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: lineage ends there, and a lost executor costs nothing."""
    path = shared_path(df.sparkSession)
    with shuffles_released(df.sparkSession):
        df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing will read again; others are left alone."""
    for table in tables:
        if (path := getattr(table, "_stored_at", None)) in WRITTEN:
            WRITTEN.remove(path)
            _delete(table.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def publish(spark: SparkSession, path: str, text: str) -> bool:
    """Write a small file that readers see whole or not at all; False if the path is taken.

    The text goes to a hidden file beside it, which is then renamed without overwriting: one atomic step on HDFS and
    its like. A local file is linked instead, since Java's rename would replace what another writer has just put there.
    """
    jvm = spark._jvm
    hadoop = jvm.org.apache.hadoop.fs
    final = hadoop.Path(path)
    fs = final.getFileSystem(spark._jsc.hadoopConfiguration())
    hidden = hadoop.Path(final.getParent(), f".{uuid.uuid4().hex}")
    out = fs.create(hidden, False)
    out.write(bytearray(text.encode()))
    out.close()
    try:
        if fs.getScheme() == "file":
            local = lambda p: jvm.java.io.File(fs.makeQualified(p).toUri().getPath()).toPath()
            jvm.java.nio.file.Files.createLink(local(final), local(hidden))
        else:
            options = spark.sparkContext._gateway.new_array(getattr(hadoop, "Options$Rename"), 0)
            hadoop.FileContext.getFileContext(fs.getUri(), spark._jsc.hadoopConfiguration()).rename(hidden, final, options)
    except Exception:
        if not fs.exists(final):
            raise
        return False
    finally:
        fs.delete(hidden, False)
    return True
