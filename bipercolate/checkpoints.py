"""Where loops cut their lineage."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where a local session names none (tests, a laptop), one temporary folder.

    On a cluster a folder of one machine would be no shared one, so that a session without the setting is an error.
    """
    context = spark.sparkContext
    folder, current = spark.conf.get("spark.checkpoint.dir", None), context._jsc.sc().getCheckpointDir()
    if not current.isEmpty():
        return folder or current.get()
    if not folder:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="bipercolate-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
    context.setCheckpointDir(folder)
    return folder


def discard(spark: SparkSession, path: str) -> None:
    """Delete a folder that ``shared_path`` named, once nothing reads it any more."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def shared_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nothing else uses."""
    return f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


#: The lists of checkpoints that open scopes will delete, the innermost last.
_scopes: ContextVar[tuple[list[DataFrame], ...]] = ContextVar("scopes", default=())


def cut(df: DataFrame) -> DataFrame:
    """``df`` written to reliable storage now and read from there, so that no later stage depends on executors' local files."""
    shared_folder(df.sparkSession)
    out = df.checkpoint(eager=True)
    if _scopes.get():
        _scopes.get()[-1].append(out)
    return out


def packed(df: DataFrame) -> DataFrame:
    """As ``cut``, in Parquet: for tables of many ids, which take a third of a checkpoint's space there."""
    spark = df.sparkSession
    path = shared_path(spark, "packed")
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._packed = path
    if _scopes.get():
        _scopes.get()[-1].append(out)
    return out


def release(df: DataFrame) -> None:
    """Delete the files of ``cut``'s or ``packed``'s result, once nothing reads it any more."""
    for scope in _scopes.get():
        scope[:] = [x for x in scope if x is not df]
    if path := getattr(df, "_packed", None):
        discard(df.sparkSession, path)
        return
    path = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
    if path.isDefined():
        discard(df.sparkSession, path.get())


@contextmanager
def scratch() -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Checkpoints made within are deleted at the end, but for those given to the function that this yields.

    Frames that leave the block must read no others. Kept ones belong to the scope around.
    """
    outer, own, kept = _scopes.get(), [], []
    token = _scopes.set((*outer, own))

    def keep(df: DataFrame) -> DataFrame:
        kept.append(df)
        return df

    try:
        yield keep
    finally:
        for df in list(own):
            if not any(df is x for x in kept):
                release(df)
        _scopes.reset(token)
        if outer:
            outer[-1].extend(x for x in own)
