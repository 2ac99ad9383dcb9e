"""Deterministic sharded WARC files: range-sorted, rolled by compressed size, committed by a manifest.

Shards are ranges of page_id of about even payload size. Their bounds follow from
running sums over all rows, not from a sample, so the same rows give the same
files, byte for byte, on any cluster. A task writes the files of a shard under
temporary names and renames each when it is whole; attempts of the same shard
write the same bytes, so a lost or repeated attempt does no harm. A reader
trusts only files that the manifest lists, with their size.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from urllib.parse import quote

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracelake.llm import common

#: A file is closed when it holds this many compressed bytes.
FILE_BYTES = 256 * 2**20
LEVEL = 4
#: Payloads from this size on become revisits of the last equal one.
REVISIT_FROM = 0
DATE = "2024-01-01T00:00:00Z"
_URN = "urn:x-tracelake:page:"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def digest(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(page_id: int | None, nth: int, url: str | None, payload: bytes, refers_to: int | None = None, date: str = DATE) -> bytes:
    """One WARC record; with ``refers_to`` a revisit, whose block has the HTTP header only."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    name = f"{_URN}{'null' if page_id is None else page_id}" + (f":{nth}" if nth else "")
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <{name}>",
        f"WARC-Date: {date}",
        *([f"WARC-Target-URI: {quote(url, safe=_SAFE)}"] if url else []),
        *([f"WARC-Refers-To: <{_URN}{refers_to}>", f"WARC-Profile: {_PROFILE}"] if refers_to is not None else []),
        f"WARC-Payload-Digest: sha1:{digest(payload)}",
        f"WARC-Block-Digest: sha1:{digest(block)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


_SAFE = "%/:=&?~#+!$,;'@()*[]"


def _gzip(data: bytes) -> bytes:
    packer = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return packer.compress(data) + packer.flush()


def _bounds(sizes: DataFrame, shard_bytes: int) -> list[int]:
    """First page_id of every shard but the first: one number for each ``shard_bytes`` of payload."""
    spark = sizes.sparkSession
    parts = sizes.groupBy("page_id").agg(F.sum("bytes").alias("bytes"))
    parts = parts.repartitionByRange(common.partitions(spark), "page_id").withColumn("part", F.spark_partition_id())
    parts = common.written(parts, "warc-sizes")
    ahead = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    whole = parts.groupBy("part").agg(F.sum("bytes").alias("whole")).select("part", F.coalesce(F.sum("whole").over(ahead), F.lit(0)).alias("ahead"))
    inside = Window.partitionBy("part").orderBy("page_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    run = parts.withColumn("upto", F.sum("bytes").over(inside)).join(whole, "part")
    shard = F.floor((F.col("ahead") + F.col("upto") - F.col("bytes")) / F.lit(shard_bytes))
    firsts = run.where("page_id is not null").groupBy(shard.alias("shard")).agg(F.min("page_id").alias("first")).collect()
    return sorted(r["first"] for r in firsts)[1:]


def _shard(page_id, bounds: list[int]):
    """How many bounds are at most ``page_id``, by a coarse and a fine look-up; null ids go first."""
    if not bounds:
        return F.lit(0)
    step = max(1, int(len(bounds) ** 0.5))
    coarse = F.array(*[F.lit(b).cast("bigint") for b in bounds[::step]])
    every = F.array(*[F.lit(b).cast("bigint") for b in bounds])
    group = F.size(F.filter(coarse, lambda b: b <= page_id))
    fine = F.slice(every, F.greatest((group - 1) * step + 1, F.lit(1)), F.lit(step))
    return F.when(page_id.isNull() | (group == 0), 0).otherwise((group - 1) * step + F.size(F.filter(fine, lambda b: b <= page_id)))


def write(pages: DataFrame, folder: str, file_bytes: int = FILE_BYTES, shard_bytes: int | None = None, revisit_from: int = REVISIT_FROM) -> DataFrame:
    """Writes a record per row of ``pages`` (page_id, url, html) and returns the manifest.

    Of rows with equal payloads of at least ``revisit_from`` bytes the one with
    the largest page_id is the response, the others revisit it; if all their ids
    are null, all are responses. Null html is an empty payload, null url leaves
    the target out. Rows that share a page_id get numbered record ids. Columns of
    the manifest: shard, number, name, bytes, records, first_page, last_page,
    sha1. An empty table gives an empty manifest. ``shard_bytes`` defaults to a
    64th of all payload, between 4 MiB and 1 GiB.
    """
    spark = pages.sparkSession
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    narrow = common.written(rows.select("page_id", F.sha1("html").alias("sha"), F.octet_length("html").cast("bigint").alias("bytes")), "warc-digests")
    equal = narrow.where(F.col("bytes") >= revisit_from).groupBy("sha", "bytes").agg(F.max("page_id").alias("refers_to"), F.count(F.lit(1)).alias("n"))
    equal = equal.where("n > 1 and refers_to is not null").select(F.col("sha").alias("s"), F.col("bytes").alias("b"), "refers_to")
    again = narrow.join(equal, (F.col("sha") == F.col("s")) & (F.col("bytes") == F.col("b"))).where(~F.col("page_id").eqNullSafe(F.col("refers_to")))
    again = again.select("page_id", "sha", "refers_to").distinct()
    if shard_bytes is None:
        total = narrow.agg(F.sum("bytes")).first()[0] or 0
        shard_bytes = min(max(total // 64, 4 * 2**20), 2**30)
    bounds = _bounds(narrow.select("page_id", "bytes"), shard_bytes)
    # A revisit's mark sorts before the rows it speaks of, in the same shard.
    marks = again.select("page_id", F.lit(None).cast("string").alias("url"), F.lit(None).cast("string").alias("html"), "sha", "refers_to")
    full = rows.select("page_id", "url", "html", F.sha1("html").alias("sha"), F.lit(None).cast("bigint").alias("refers_to"))
    both = full.unionByName(marks).withColumn("shard", _shard(F.col("page_id"), bounds))
    both = both.repartition(max(1, len(bounds) + 1), "shard").sortWithinPartitions("shard", "page_id", F.col("refers_to").desc_nulls_last(), "sha", "url")

    def put(batches):
        files = _Files(folder, file_bytes)
        marked: dict[tuple, int] = {}
        last, nth = object(), 0
        for batch in batches:
            cols = [batch.column(k) for k in ("shard", "page_id", "url", "html", "sha", "refers_to")]
            for k in range(batch.num_rows):
                shard, page, url, html, sha, refers = (c[k].as_py() for c in cols)
                if (shard, page) != last:
                    last, nth, marked = (shard, page), 0, {}
                if refers is not None:
                    marked[(page, sha)] = refers
                    continue
                files.add(shard, page, _gzip(record(page, nth, url, html.encode(), marked.get((page, sha)))))
                nth += 1
        files.close()
        if files.done:
            yield pa.RecordBatch.from_pylist(files.done, schema=_MANIFEST)

    fields = "shard bigint, number bigint, name string, bytes bigint, records bigint, first_page bigint, last_page bigint, sha1 string"
    made = both.mapInArrow(put, fields)
    made.write.mode("overwrite").parquet(f"{folder}/_manifest")
    return spark.read.schema(made.schema).parquet(f"{folder}/_manifest")


_MANIFEST = pa.schema([(n, pa.string() if n in ("name", "sha1") else pa.int64()) for n in ("shard", "number", "name", "bytes", "records", "first_page", "last_page", "sha1")])


class _Files:
    """The files of a task: one open at a time, renamed to its name when whole."""

    def __init__(self, folder: str, most: int) -> None:
        self.fs, self.path = fs.FileSystem.from_uri(folder)
        self.most, self.done, self.out = most, [], None

    def add(self, shard: int, page: int | None, data: bytes) -> None:
        if self.out is not None and (self.now["shard"] != shard or self.now["bytes"] + len(data) > self.most):
            self.close()
        if self.out is None:
            same = [d for d in self.done if d["shard"] == shard]
            name = f"shard-{shard:06d}-{len(same):05d}.warc.gz"
            self.now = {"shard": shard, "number": len(same), "name": name, "bytes": 0, "records": 0, "first_page": page, "last_page": page}
            self.hash = hashlib.sha1()
            self.temp = f"{self.path}/_temporary/{name}.{uuid.uuid4().hex}"
            self.fs.create_dir(f"{self.path}/_temporary", recursive=True)
            self.out = self.fs.open_output_stream(self.temp, compression=None)
        self.out.write(data)
        self.hash.update(data)
        self.now["bytes"] += len(data)
        self.now["records"] += 1
        self.now["last_page"] = page

    def close(self) -> None:
        if self.out is None:
            return
        self.out.close()
        self.out = None
        target = f"{self.path}/{self.now['name']}"
        try:
            self.fs.move(self.temp, target)
        except OSError:  # a store that doesn't rename over another attempt's file
            found = self.fs.get_file_info(target)
            if found.type != fs.FileType.File or found.size != self.now["bytes"]:
                raise
            self.fs.delete_file(self.temp)
        self.done.append(self.now | {"sha1": self.hash.hexdigest()})


def records(stream):
    """(headers, block) of each record of an open, record-wise compressed file."""
    data, unpack, out = b"", zlib.decompressobj(31), []
    while True:
        if not data:
            data = stream.read(2**20)
            if not data:
                if out:
                    raise ValueError("the file ends within a record")
                return
        out.append(unpack.decompress(data))
        data = b""
        if unpack.eof:
            data = unpack.unused_data
            head, _, rest = b"".join(out).partition(b"\r\n\r\n")
            lines = head.decode().split("\r\n")
            headers = dict(line.split(": ", 1) for line in lines[1:])
            yield headers, rest[: int(headers["Content-Length"])]
            unpack, out = zlib.decompressobj(31), []


def _page(urn: str | None) -> int | None:
    part = urn.strip("<>").removeprefix(_URN).split(":")[0] if urn else "null"
    return None if part == "null" else int(part)


def read(spark: SparkSession, folder: str) -> DataFrame:
    """Per record of the files in the manifest: page_id, url, payload, payload_bytes, payload_digest, record_type, refers_to.

    Sizes, block digests and, for responses, payload digests are verified;
    anything else raises. A revisit has a null payload and the size and digest of
    the payload that it stands for.
    """
    listed = spark.read.parquet(f"{folder}/_manifest").select("name", "bytes")
    files = listed.repartition(max(1, listed.count()), "name")

    def get(batches):
        store, path = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for name, size in zip(batch.column("name").to_pylist(), batch.column("bytes").to_pylist()):
                if store.get_file_info(f"{path}/{name}").size != size:
                    raise ValueError(f"{name} isn't as long as the manifest says")
                held, weight = [], 0
                with store.open_input_stream(f"{path}/{name}", compression=None) as stream:
                    for headers, block in records(stream):
                        if headers["WARC-Block-Digest"] != f"sha1:{digest(block)}":
                            raise ValueError(f"{name}: {headers['WARC-Record-ID']} is damaged")
                        http, _, payload = block.partition(b"\r\n\r\n")
                        told = headers["WARC-Payload-Digest"].removeprefix("sha1:")
                        response = headers["WARC-Type"] == "response"
                        if response and digest(payload) != told:
                            raise ValueError(f"{name}: the payload of {headers['WARC-Record-ID']} is damaged")
                        length = int(http.decode().rpartition("Content-Length: ")[2])
                        held.append({
                            "page_id": _page(headers["WARC-Record-ID"]), "url": headers.get("WARC-Target-URI"), "payload": payload if response else None, "payload_bytes": length,
                            "payload_digest": told, "record_type": headers["WARC-Type"], "refers_to": None if response else _page(headers["WARC-Refers-To"]),
                        })
                        weight += length + 500
                        if weight > 8 * 2**20:
                            yield pa.RecordBatch.from_pylist(held, schema=_RECORD)
                            held, weight = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist(held, schema=_RECORD)

    return files.mapInArrow(get, "page_id bigint, url string, payload binary, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint")


_RECORD = pa.schema([
    ("page_id", pa.int64()), ("url", pa.string()), ("payload", pa.binary()), ("payload_bytes", pa.int64()),
    ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()),
])
