"""Column expressions of the model: identity, direction, category, dependency."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracelake.model import schema


def process_key(host: Column, exe: Column, pid: Column) -> Column:
    """A process is its host, executable and pid."""
    return F.concat(F.lit("p:"), host, F.lit(":"), exe, F.lit(":"), pid.cast("string"))


def file_key(host: Column, path: Column) -> Column:
    """A file is its host and absolute path."""
    return F.concat(F.lit("f:"), host, F.lit(":"), path)


def socket_key(protocol: Column, src_ip: Column, src_port: Column, dst_ip: Column, dst_port: Column) -> Column:
    """A socket is its five values; it has no host, so flows can pass between hosts."""
    return F.concat(F.lit("n:"), protocol, F.lit(":"), src_ip, F.lit(":"), src_port.cast("string"), F.lit(":"), dst_ip, F.lit(":"), dst_port.cast("string"))


def inward(op: Column) -> Column:
    """Whether information flows from the object to the subject."""
    return op.isin(*schema.INWARD)


def category(op: Column) -> Column:
    """Category of an event by its operation; null for one that is unknown."""
    out = None
    for name, ops in schema.OPS.items():
        out = F.when(op.isin(*ops), name) if out is None else out.when(op.isin(*ops), name)
    return out


def orient(events: DataFrame) -> DataFrame:
    """Adds src_id and dst_id, the direction of the flow, from op, subject_id and object_id."""
    towards = inward(F.col("op"))
    return events.withColumn("src_id", F.when(towards, F.col("object_id")).otherwise(F.col("subject_id"))).withColumn(
        "dst_id", F.when(towards, F.col("subject_id")).otherwise(F.col("object_id"))
    )


def depends(a: str, b: str, order: str = "formula") -> Column:
    """Whether edge b depends on edge a (struct column names): a's sink is b's source and a starts before b ends.

    With ``order="start"`` a must also start no later than b.
    """
    rule = (F.col(f"{a}.dst_id") == F.col(f"{b}.src_id")) & (F.col(f"{a}.start_us") < F.col(f"{b}.end_us"))
    return rule & (F.col(f"{a}.start_us") <= F.col(f"{b}.start_us")) if order == "start" else rule


def micros(ts: Column) -> Column:
    """Microseconds since the epoch of a timestamp, with or without zone (session zone UTC)."""
    return F.unix_micros(ts.cast("timestamp"))


def within(first: Column, second: Column, bound_us: int, ordered: bool = True) -> Column:
    """Starts at most ``bound_us`` apart (less than); ordered: the second not before the first."""
    gap = second - first
    return (gap >= 0) & (gap < bound_us) if ordered else F.abs(gap) < bound_us
