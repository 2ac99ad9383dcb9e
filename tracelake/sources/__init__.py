"""Sources of raw audit records: parsers of two styles of log, a data source for both, file formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_LINE = r"^(\d+) (\S+) (\S+)\((\d+)\) ([a-z]+) (\S+)(?: res=(-?\d+))?(?: latency=(\d+))?$"
PARSED = "seen_us bigint, host string, exe_name string, pid bigint, op string, object string, amount bigint, duration_us bigint"


def parse_syscall_lines(lines: DataFrame, column: str = "value") -> DataFrame:
    """``<microseconds> <host> <exe>(<pid>) <op> <object> [res=<bytes>] [latency=<us>]`` to columns; bad lines have nulls and the raw text.

    Whatever is not understood stays in ``rest`` as it came.
    """
    part = lambda k: F.nullif(F.regexp_extract(column, _LINE, k), F.lit(""))
    return lines.select(
        part(1).cast("bigint").alias("seen_us"), part(2).alias("host"), part(3).alias("exe_name"), part(4).cast("bigint").alias("pid"), part(5).alias("op"), part(6).alias("object"),
        F.coalesce(part(7).cast("bigint"), F.lit(0)).alias("amount"), F.coalesce(part(8).cast("bigint"), F.lit(0)).alias("duration_us"),
        F.when(~F.col(column).rlike(_LINE), F.col(column)).alias("rest"),
    )


def parse_monitor_csv(lines: DataFrame, column: str = "value") -> DataFrame:
    """``time,host,process,pid,operation,path,detail`` rows to the same columns; detail is a JSON text with Length and Duration."""
    row = F.from_csv(column, "seen_us bigint, host string, exe_name string, pid bigint, op string, object string, detail string", {"quote": '"', "escape": '"'})
    ops = F.create_map(*[F.lit(x) for pair in {"ReadFile": "read", "WriteFile": "write", "TCP Send": "sendto", "TCP Receive": "recvfrom", "Process Create": "start", "Process Exit": "end"}.items() for x in pair])
    detail = F.try_parse_json("r.detail")
    return lines.select(row.alias("r")).select(
        "r.seen_us", "r.host", "r.exe_name", "r.pid", F.coalesce(ops[F.col("r.op")], F.lower("r.op")).alias("op"), "r.object",
        F.coalesce(F.try_variant_get(detail, "$.Length", "bigint"), F.lit(0)).alias("amount"), F.coalesce(F.try_variant_get(detail, "$.Duration", "bigint"), F.lit(0)).alias("duration_us"), F.lit(None).cast("string").alias("rest"),
    )


class AuditLogSource(DataSource):
    """``spark.read.format("auditlog").option("path", folder)``: one partition per file, lines parsed in the reader.

    With ``option("rest", "true")`` lines that aren't understood come as well, as
    they are, in one more column ``rest``; without it they are passed over.

    The folder must be one that every executor reaches as a path.
    """

    @classmethod
    def name(cls) -> str:
        return "auditlog"

    def schema(self) -> str:
        return f"{PARSED}, rest string" if _wants_rest(self.options) else PARSED

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def _wants_rest(options) -> bool:
    return str(options.get("rest", "false")).lower() == "true"


class _Reader(DataSourceReader):
    def __init__(self, options) -> None:
        self.path, self.rest = options["path"], _wants_rest(options)

    def partitions(self):
        from pathlib import Path

        return [InputPartition(str(p)) for p in sorted(Path(self.path).glob("*.log"))]

    def read(self, partition):
        import re

        with open(partition.value) as lines:
            for line in lines:
                line = line.rstrip("\n")
                if m := re.match(_LINE, line):
                    row = int(m[1]), m[2], m[3], int(m[4]), m[5], m[6], int(m[7] or 0), int(m[8] or 0)
                    yield (*row, None) if self.rest else row
                elif self.rest:
                    yield (*[None] * 8, line)


def to_lines(events: DataFrame) -> DataFrame:
    """Oriented events as lines of the first style, for tests and for sinks."""
    exe, pid = F.split_part("subject_id", F.lit(":"), F.lit(3)), F.split_part("subject_id", F.lit(":"), F.lit(4))
    return events.select(F.concat(F.col("start_us").cast("string"), F.lit(" "), "host", F.lit(" "), exe, F.lit("("), pid, F.lit(") "), "op", F.lit(" "), "object_id", F.lit(" res="), F.col("amount").cast("string"), F.lit(" latency="), F.col("duration_us").cast("string")).alias("value"))


def read_any(spark: SparkSession, path: str, fmt: str, schema=None) -> DataFrame:
    """Parquet, ORC, JSON lines, CSV or text; text formats want a schema."""
    reader = spark.read.format(fmt)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.option("header", "true").load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str | None = None, parts: int = 1, columns: list[str] | None = None, **options: str) -> DataFrame:
    """A table of a relational store, read in ``parts`` ranges of the whole-number ``column``.

    The bounds come from one query that the database answers. They only deal
    rows to tasks: rows beyond them, and nulls, are read as well. Filters and
    column lists go to the database. Without ``column`` one task reads all.
    """
    reader = spark.read.format("jdbc").option("url", url).options(**options)
    if column is not None and parts > 1:
        quoted = spark._jvm.org.apache.spark.sql.jdbc.JdbcDialects.get(url).quoteIdentifier(column)
        ends = reader.option("query", f"SELECT MIN({quoted}) AS low_end, MAX({quoted}) AS high_end FROM {table}").load().first()
        reader = spark.read.format("jdbc").option("url", url).options(**options)
        if ends[0] is not None and ends[0] < ends[1]:
            reader = reader.option("partitionColumn", column).option("lowerBound", str(int(ends[0]))).option("upperBound", str(int(ends[1]) + 1)).option("numPartitions", str(parts))
    out = reader.option("dbtable", table).load()
    return out if columns is None else out.select(*columns)
