"""The given tables seen as event histories, in Spark; ``oracle.py`` has the same in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracelake import functions as X
from tracelake.model import schema
from tracelake.model.store import TraceStore

# The operation that an event type stands for.
_OP = {"view": "read", "purchase": "write", "click": "recvfrom", "error": "sendto", "signup": "clone"}
_SHARED = 30


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _with_all(df: DataFrame, columns: list[str]) -> DataFrame:
    kinds = {f.name: f.dataType for f in schema.entity_schema()}
    return df.select(*[F.col(c) if c in df.columns else F.lit(None).cast(kinds[c]).alias(c) for c in columns])


def _host(user: Column) -> Column:
    return F.concat(F.lit("host"), (user % 3 + 1).cast("string"))


def _users(spark: SparkSession, sf_dir: str) -> DataFrame:
    people = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"), "left")
    people = people.join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"), "left")
    exe = F.lower("c_mktsegment")
    return people.select(
        F.col("c_custkey").alias("user_id"), exe.alias("exe"), F.col("n_name").alias("owner"), F.col("r_name").alias("owner_group"),
        X.process_key(_host(F.col("c_custkey")), exe, F.col("c_custkey")).alias("process_id"),
    )


def _files(spark: SparkSession, sf_dir: str) -> DataFrame:
    name = F.concat(F.replace("p_name", F.lit(" "), F.lit("_")), F.lit("."), F.lower("p_type"))
    path = F.concat(F.lit("/"), F.replace(F.lower("p_brand"), F.lit("#"), F.lit("")), F.lit("/"), F.col("p_partkey").cast("string"), F.lit("/"), name)
    return table(spark, sf_dir, "part").where("p_partkey < 100").select(F.col("p_partkey").alias("k"), name.alias("file_name"), path.alias("path"))


def _socket(k: Column, host: Column) -> dict[str, Column]:
    shared = k < _SHARED
    number = F.substring(host, 5, 9)
    return {
        "src_ip": F.when(shared, F.lit("10.0.0.1")).otherwise(F.concat(F.lit("10.0."), number, F.lit(".1"))),
        "src_port": F.when(shared, 30000 + k).otherwise(40000 + k).cast("int"),
        "dst_ip": F.when(shared, F.lit("10.0.0.2")).otherwise(F.concat(F.lit("203.0.113."), k.cast("string"))),
        "dst_port": F.when(shared, 22).otherwise(443).cast("int"),
    }


def events(spark: SparkSession, sf_dir: str) -> TraceStore:
    """Clicks, views and so on as the doings of processes on three hosts."""
    raw = table(spark, sf_dir, "events")
    users, files = _users(spark, sf_dir), _files(spark, sf_dir)
    most = raw.agg((F.floor((F.max("user_id") + 1) / 3)).alias("third"))
    op = F.create_map(*[F.lit(x) for pair in _OP.items() for x in pair])[F.col("event_type")]
    rows = raw.crossJoin(F.broadcast(most)).select(  # one row
        "event_id", "user_id", _host(F.col("user_id")).alias("host"), op.alias("op"), F.get_json_object("props", "$.k").cast("bigint").alias("k"), "third",
        X.micros(F.col("ts")).alias("start_us"), F.round(F.col("value") * 1e6).cast("bigint").alias("duration_us"), F.round(F.col("value") * 100).cast("bigint").alias("amount"),
    )
    rows = rows.withColumn("other", 3 * (F.col("k") % F.col("third")) + F.col("user_id") % 3)
    subject = users.select(F.col("user_id").alias("u"), F.col("process_id").alias("subject_id"))
    target = users.select(F.col("user_id").alias("o"), F.col("process_id").alias("target_id"))
    rows = rows.join(subject, F.col("user_id") == F.col("u")).join(target, F.col("other") == F.col("o"), "left").join(files, "k", "left")
    socket = _socket(F.col("k"), F.col("host"))
    socket_id = X.socket_key(F.lit("tcp"), socket["src_ip"], socket["src_port"], socket["dst_ip"], socket["dst_port"])
    rows = rows.withColumn("category", X.category(F.col("op")))
    rows = rows.withColumn(
        "object_id", F.when(F.col("category") == "file", X.file_key(F.col("host"), F.col("path"))).when(F.col("category") == "network", socket_id).otherwise(F.col("target_id"))
    )
    rows = X.orient(rows).withColumn("end_us", F.col("start_us") + F.col("duration_us"))
    rows = rows.withColumn("day", F.to_date(F.timestamp_micros("start_us"))).select(*schema.EVENT_COLUMNS)

    pairs = raw.select(_host(F.col("user_id")).alias("host"), F.get_json_object("props", "$.k").cast("bigint").alias("k"), "event_type").distinct()
    touched = pairs.where(F.col("event_type").isin("view", "purchase")).select("host", "k").distinct().join(files, "k")
    file_rows = touched.select(X.file_key(F.col("host"), F.col("path")).alias("entity_id"), F.lit("file").alias("kind"), "host", F.col("file_name").alias("name"), "path")
    wire = pairs.where(F.col("event_type").isin("click", "error")).select("host", "k").distinct()
    parts = _socket(F.col("k"), F.col("host"))
    wire = wire.select(*[c.alias(n) for n, c in parts.items()]).distinct().withColumn("protocol", F.lit("tcp"))
    wire_id = X.socket_key(F.col("protocol"), F.col("src_ip"), F.col("src_port"), F.col("dst_ip"), F.col("dst_port"))
    wire = wire.withColumn("entity_id", wire_id).withColumn("kind", F.lit("network")).withColumn("name", F.substring("entity_id", 3, 200))
    active = raw.select("user_id").distinct().join(users, "user_id")
    cloned = rows.where("op = 'clone'").select(F.col("object_id").alias("process_id")).distinct().join(users, "process_id").select(*active.columns)
    people = active.unionByName(cloned).distinct()
    people = people.select(
        F.col("process_id").alias("entity_id"), F.lit("process").alias("kind"), _host(F.col("user_id")).alias("host"), F.col("exe").alias("name"), F.concat(F.lit("/bin/"), "exe").alias("path"),
        F.col("exe").alias("exe_name"), F.concat(F.lit("/bin/"), "exe").alias("exe_path"), F.concat(F.col("exe"), F.lit(" --acct "), F.col("user_id").cast("string")).alias("cmdline"),
        F.col("user_id").alias("pid"), "owner", "owner_group",
    )
    entities = _with_all(people, schema.ENTITY_COLUMNS)
    for part in (file_rows, wire):
        entities = entities.unionByName(_with_all(part, schema.ENTITY_COLUMNS))
    return TraceStore(entities, rows)


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders and line items as edges, with many equal times and hot sinks: event_id, op, src_id, dst_id, start_us, end_us, amount."""
    nation, supplier = table(spark, sf_dir, "nation"), table(spark, sf_dir, "supplier")
    order_key = F.concat(F.lit("p:order:"), F.col("o_orderkey").cast("string"))
    orders = table(spark, sf_dir, "orders").select(
        F.col("o_orderkey").alias("event_id"), F.lit("clone").alias("op"), F.concat(F.lit("p:customer:"), F.col("o_custkey").cast("string")).alias("src_id"), order_key.alias("dst_id"),
        X.micros(F.col("o_orderdate")).alias("start_us"), X.micros(F.col("o_orderdate")).alias("end_us"), F.round(F.col("o_totalprice") * 100).cast("bigint").alias("amount"),
    )
    items = table(spark, sf_dir, "lineitem").join(supplier.join(nation, F.col("s_nationkey") == F.col("n_nationkey")), F.col("l_suppkey") == F.col("s_suppkey"))
    vendor = F.concat(F.lit("p:supplier:"), F.col("l_suppkey").cast("string"))
    part = F.concat(F.lit("f:part:"), F.col("l_partkey").cast("string"))
    order = F.concat(F.lit("p:order:"), F.col("l_orderkey").cast("string"))
    wire = F.concat(F.lit("n:nation:"), F.col("n_name"))
    op = F.when(F.col("l_linestatus") == "F", "write").when(F.col("l_returnflag") == "R", "sendto").otherwise("read")
    start = X.micros(F.col("l_shipdate"))
    items = items.select(
        (F.lit(10**12) + F.col("l_orderkey") * 1000 + F.col("l_linenumber") * 100).alias("base"), op.alias("op"),
        F.when(op == "write", vendor).when(op == "sendto", order).otherwise(part).alias("src_id"), F.when(op == "write", part).when(op == "sendto", wire).otherwise(order).alias("dst_id"),
        start.alias("start_us"), (start + F.round(F.col("l_quantity") * 1e6).cast("bigint")).alias("end_us"), F.round(F.col("l_extendedprice") * 100).cast("bigint").alias("amount"),
    )
    nth = F.row_number().over(Window.partitionBy("base").orderBy("op", "src_id", "dst_id", "start_us", "end_us", "amount")) - 1
    items = items.withColumn("event_id", F.col("base") + nth).select(*orders.columns)
    return orders.unionByName(items)


def chain(spark: SparkSession, sf_dir: str, long_links: int = 0) -> DataFrame:
    """Conversations as chains of processes that read the last turn's file and write their own.

    With ``long_links`` the first process of conversation c + 1 also reads the
    last file of conversation c, for c below that number: one chain of many levels.
    """
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role").distinct()
    pid = F.concat(F.lit("p:host1:"), F.col("role"), F.lit(":"), (F.col("conv_id") * 100 + F.col("turn")).cast("string"))
    file = lambda conv, turn: F.concat(F.lit("f:host1:/conv/"), conv.cast("string"), F.lit("/"), turn.cast("string"))
    base = F.col("conv_id") * 10**9 + F.col("turn") * 10**6
    number = F.col("conv_id") * 1000 + F.col("turn") * 10
    writes = turns.select((number + 1).alias("event_id"), F.lit("write").alias("op"), pid.alias("src_id"), file(F.col("conv_id"), F.col("turn")).alias("dst_id"), base.alias("start_us"), base.alias("end_us"))
    early = base - 500_000
    reads = turns.where("turn > 0").select(
        (number + 2).alias("event_id"), F.lit("read").alias("op"), file(F.col("conv_id"), F.col("turn") - 1).alias("src_id"), pid.alias("dst_id"), early.alias("start_us"), early.alias("end_us")
    )
    out = writes.unionByName(reads)
    if long_links:
        last = turns.where(F.col("conv_id") < long_links).groupBy(F.col("conv_id").alias("c")).agg(F.max("turn").alias("t"))
        heads = turns.where("turn = 0").join(last, F.col("conv_id") == F.col("c") + 1)
        out = out.unionByName(
            heads.select((number + 3).alias("event_id"), F.lit("read").alias("op"), file(F.col("c"), F.col("t")).alias("src_id"), pid.alias("dst_id"), early.alias("start_us"), early.alias("end_us"))
        )
    return out


def web(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page addresses as network entities; the page's content is never read: page_id, scheme, dst_host, path, page, language."""
    pages = table(spark, sf_dir, "pages")
    url = F.col("url")
    return pages.select(
        "page_id", F.parse_url(url, F.lit("PROTOCOL")).alias("scheme"), F.parse_url(url, F.lit("HOST")).alias("dst_host"), F.parse_url(url, F.lit("PATH")).alias("path"),
        F.parse_url(url, F.lit("QUERY"), F.lit("page")).alias("page"), F.split_part(F.parse_url(url, F.lit("PATH")), F.lit("/"), F.lit(2)).alias("language"),
    )


def leak(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies: the first document of an equal text flows to each later one: src_doc, dst_doc."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.xxhash64("text").alias("h"), F.sha2("text", 256).alias("s"))
    first = docs.groupBy("h", "s").agg(F.min("doc_id").alias("src_doc"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return docs.join(first, ["h", "s"]).where("doc_id > src_doc").select("src_doc", F.col("doc_id").alias("dst_doc"))
