"""Lineage cuts as Parquet tables in the folder that the whole cluster shares."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a local master without one gets a temporary folder, a cluster is an error."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster shares")
    made = tempfile.mkdtemp(prefix="pathtwin-")
    spark.sparkContext.setCheckpointDir(made)
    return spark.sparkContext.getCheckpointDir().rstrip("/")


#: Tables made in open scopes, innermost last.
_SCOPES: list[list[DataFrame]] = []


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` once into the shared folder and return a scan of it: later reads survive lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    if _SCOPES:
        _SCOPES[-1].append(out)
    return out


@contextmanager
def scope() -> Iterator[None]:
    """Deletes at its end every table that was cut inside. What is to outlive it is cut after it, or written elsewhere inside."""
    _SCOPES.append([])
    try:
        yield
    finally:
        for df in _SCOPES.pop():
            drop(df)


def settled(make: Callable[[], DataFrame]) -> DataFrame:
    """The table that ``make`` plans, cut, with all that was cut on the way to it deleted."""
    with scope():
        out = cut(make())
        _SCOPES[-1].pop()
    if _SCOPES:
        _SCOPES[-1].append(out)
    return out


def drop(df: DataFrame) -> None:
    """Delete the table behind a ``cut`` that no later plan reads."""
    path = getattr(df, "_cut_path", None)
    if path:
        jvm = df.sparkSession._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)
