"""Plan helpers: written intermediate tables, planner statistics, abstract costs."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """Folder that all executors reach: ``spark.checkpoint.dir``, else (on one machine) a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = spark.conf.get("tracelake.shared.dir", None)
    if not own:
        own = "file://" + tempfile.mkdtemp(prefix="tracelake-")
        spark.conf.set("tracelake.shared.dir", own)
    return own


_written: list[str] = []


def cleanup(spark: SparkSession) -> None:
    """Removes the tables that this process wrote; results that still read them must be gone or stored elsewhere."""
    while _written:
        where, fs = _place(spark, _written.pop())
        fs.delete(where, True)


def write(df: DataFrame, name: str = "step") -> str:
    """Writes ``df`` to the shared folder; the path."""
    path = f"{shared_dir(df.sparkSession)}/tracelake/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append(path)
    return path


def pin(df: DataFrame, name: str = "step") -> DataFrame:
    """``df`` written to the shared folder and read back: cuts the lineage and survives lost executors."""
    return df.sparkSession.read.schema(df.schema).parquet(write(df, name))


def _place(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where, where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def exists(spark: SparkSession, path: str) -> bool:
    where, fs = _place(spark, path)
    return bool(fs.exists(where))


def state_of(spark: SparkSession, folder: str) -> tuple:
    """Name, time, bytes and number of files of each table of a folder: differs once a table is written again."""
    where, fs = _place(spark, folder)
    out = []
    for status in fs.listStatus(where):
        held = fs.getContentSummary(status.getPath())
        out.append((status.getPath().toString(), status.getModificationTime(), held.getLength(), held.getFileCount()))
    return tuple(sorted(out))


def input_bytes(df: DataFrame) -> int:
    """Bytes of all inputs of a plan as far as they are known, without running anything."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(str(leaves.apply(k).stats().sizeInBytes())) for k in range(leaves.size())]
    return sum(s for s in sizes if s < 2**62)


def up_to(df: DataFrame, rows: int, bytes_: int = 4 * 2**30) -> DataFrame | None:
    """``df``, written, if it has at most so many rows; None for more.

    Inputs of more than ``bytes_`` are not looked at. Below, the rows are written
    once, which serves both the count and what reads them then.
    """
    if input_bytes(df) > bytes_:
        return None
    held = pin(df.limit(rows + 1), "small")
    return held if held.count() <= rows else None


def estimate(df: DataFrame) -> dict[str, float]:
    """Spark's own estimates for the optimised plan: bytes, and rows where it knows them."""
    stats = df._jdf.queryExecution().optimizedPlan().stats()
    rows = stats.rowCount()
    return {"bytes": float(str(stats.sizeInBytes())), "rows": float(str(rows.get())) if rows.isDefined() else float("nan")}


def operators(df: DataFrame) -> list[str]:
    """Names of the operators of the physical plan, top first."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return [m for m in re.findall(r"(?:\+-|\:-|^)\s*(?:\*\(\d+\)\s*)?([A-Z]\w+)", text, flags=re.M)]
