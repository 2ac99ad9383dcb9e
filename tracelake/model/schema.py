"""Schemas and value domains of entities and events."""

from __future__ import annotations

from pyspark.sql import types as T

KINDS = ("process", "file", "network")
CATEGORIES = KINDS
# Operations by the category of their object.
OPS = {
    "file": ("read", "readv", "write", "writev", "execve", "rename"),
    "network": ("recvfrom", "sendto"),
    "process": ("fork", "clone", "start", "end"),
}
#: Operations by which information flows from the object to the subject; by all others it flows the other way.
INWARD = ("read", "readv", "recvfrom", "execve")

# Attribute names of the language and the columns that hold them.
ENTITY_TEXT = {"type": "kind", "name": "name", "path": "path", "dstip": "dst_ip", "srcip": "src_ip", "exename": "exe_name", "exepath": "exe_path", "cmdline": "cmdline", "host": "host"}
ENTITY_NUMBER = {"pid": "pid", "srcport": "src_port", "dstport": "dst_port"}
EVENT_TEXT = {"optype": "op", "srcid": "src_id", "dstid": "dst_id", "host": "host"}
EVENT_NUMBER = {"id": "event_id", "starttime": "start_us", "endtime": "end_us", "amount": "amount"}
#: Attributes that only entities of some kinds have.
ONLY = {"path": ("process", "file"), "exename": ("process",), "exepath": ("process",), "cmdline": ("process",), "pid": ("process",), "srcip": ("network",), "dstip": ("network",), "srcport": ("network",), "dstport": ("network",)}


def entity_schema() -> T.StructType:
    text = ["entity_id", "kind", "host", "name", "path", "exe_name", "exe_path", "cmdline", "owner", "owner_group", "src_ip", "dst_ip", "protocol"]
    fields = [T.StructField(n, T.StringType(), n not in ("entity_id", "kind")) for n in text]
    fields += [T.StructField("pid", T.LongType()), T.StructField("src_port", T.IntegerType()), T.StructField("dst_port", T.IntegerType())]
    return T.StructType(fields)


def event_schema() -> T.StructType:
    kinds = {"event_id": T.LongType(), "start_us": T.LongType(), "end_us": T.LongType(), "duration_us": T.LongType(), "amount": T.LongType(), "day": T.DateType()}
    names = ["event_id", "host", "category", "op", "subject_id", "object_id", "src_id", "dst_id", "start_us", "end_us", "duration_us", "amount", "day"]
    return T.StructType([T.StructField(n, kinds.get(n, T.StringType()), n not in ("event_id", "src_id", "dst_id")) for n in names])


ENTITY_COLUMNS = entity_schema().fieldNames()
EVENT_COLUMNS = event_schema().fieldNames()
EDGE_COLUMNS = ["event_id", "src_id", "dst_id", "start_us", "end_us"]
