"""Shared plumbing of the training-data operators: written tables, exact ranks."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters that part words: blank, tab, line feed, vertical tab, form feed, return.
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only where the session names none (tests on one machine) a temporary folder
    is made, once for the session.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = spark.conf.get("tracelake.shared.dir", None)
    if not own:
        own = "file://" + tempfile.mkdtemp(prefix="tracelake-")
        spark.conf.set("tracelake.shared.dir", own)
    return own


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/tracelake/{name}-{uuid.uuid4().hex}"


#: Rows and bytes of an Arrow batch, where the session doesn't say.
BATCH = {"spark.sql.execution.arrow.maxRecordsPerBatch": "1000", "spark.sql.execution.arrow.maxBytesPerBatch": "16m"}


def small_batches(spark: SparkSession) -> None:
    """Bounds Arrow batches of this session, unless it has bounds of its own.

    Both the executor and its Python workers hold whole batches; the usual
    10,000 rows of long texts are hundreds of MB.
    """
    for key, value in BATCH.items():
        if spark.conf.get(key, None) is None:
            spark.conf.set(key, value)


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once to the shared folder and read back.

    This cuts the lineage: later jobs, and retries after a lost executor, start
    from files that every executor can read.
    """
    spark = df.sparkSession
    small_batches(spark)
    path = new_folder(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._tracelake_path = path
    _made.add(path)
    return out


def drop_written(df: DataFrame) -> None:
    """Remove a table made by :func:`written` that nothing reads any more."""
    path = getattr(df, "_tracelake_path", None)
    if path:
        _delete(df.sparkSession, path)


def cleanup(spark: SparkSession) -> None:
    """Removes all tables that this process wrote; results that still read them must be gone or stored elsewhere."""
    for path in list(_made):
        _delete(spark, path)


_made: set[str] = set()


def _delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _made.discard(path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def slice_bits(rows: int, least: int = 6, most: int = 24, rows_each: int = 1_000_000) -> int:
    """How many top bits of a hash cut ``rows`` rows into slices of about ``rows_each``, whatever the number of rows."""
    return min(max(least, (max(rows, 1) // rows_each).bit_length()), most)


def word_count(text: Column) -> Column:
    """Number of words of a text as a long; null counts as an empty text."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Names for helper columns that clash with none of ``df``'s."""
    have = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in have:
            name = f"_{name}"
        have.add(name.lower())
        out.append(name)
    return out
