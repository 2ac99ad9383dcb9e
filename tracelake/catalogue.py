"""Queries of the general operators: sources' functions, joins, aggregates, windows, sets, nested types."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tracelake import operators as O  # noqa: N812
from tracelake.functions import micros
from tracelake.model.views import table
from tracelake.workloads import register

_H = 3_600_000_000
_E = "(SELECT event_id, user_id, event_type, value, epoch_us(ts) AS t, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events)"


def _ev(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "value", micros(F.col("ts")).alias("t"), F.get_json_object("props", "$.k").cast("bigint").alias("k"))


def _kind(df, kind, **names):
    return df.where(F.col("event_type") == kind).select(*[F.col(a).alias(b) for b, a in names.items()])


@register("op_join_band", f"SELECT a.event_id AS a_id, b.event_id AS b_id FROM {_E} a JOIN {_E} b USING (user_id) WHERE a.event_type = 'view' AND b.event_type = 'error' AND b.t - a.t >= 0 AND b.t - a.t < {_H}")
def join_band(spark, sf_dir):
    e = _ev(spark, sf_dir)
    a, b = _kind(e, "view", user_id="user_id", a_id="event_id", a_t="t"), _kind(e, "error", user_id="user_id", b_id="event_id", b_t="t")
    return O.band_join(a, b, ["user_id"], "a_t", "b_t", _H).select("a_id", "b_id")


@register("op_join_asof", f"SELECT a.event_id, (SELECT max(b.t) FROM {_E} b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND b.t < a.t) AS last_t FROM {_E} a WHERE a.event_type = 'view'")
def join_asof(spark, sf_dir):
    e = _ev(spark, sf_dir)
    a, b = _kind(e, "view", user_id="user_id", event_id="event_id", t="t"), _kind(e, "purchase", user_id="user_id", p_t="t", p_v="t")
    return O.as_of_join(a, b, "user_id", "t", "p_t", "p_v", "last_t").select("event_id", "last_t")


@register("op_join_overlap", f"SELECT a.event_id AS a_id, b.event_id AS b_id FROM {_E} a JOIN {_E} b USING (user_id) WHERE a.event_type = 'click' AND b.event_type = 'view' AND a.t <= b.t + {_H} AND b.t <= a.t + {_H}")
def join_overlap(spark, sf_dir):
    e = _ev(spark, sf_dir)
    a = _kind(e, "click", user_id="user_id", a_id="event_id", a_from="t").withColumn("a_to", F.col("a_from") + _H)
    b = _kind(e, "view", user_id="user_id", b_id="event_id", b_from="t").withColumn("b_to", F.col("b_from") + _H)
    return O.overlap_join(a, b, "user_id", ("a_from", "a_to"), ("b_from", "b_to"), 2 * _H).select("a_id", "b_id")


@register("op_join_skewed", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def join_skewed(spark, sf_dir):
    people = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return O.salted_join(_ev(spark, sf_dir).select("user_id", "event_id"), people, "user_id", 4, F.col("event_id")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@register("op_join_outer", "SELECT c_custkey, user_id, coalesce(n, 0) AS n FROM customer FULL JOIN (SELECT user_id, count(*) AS n FROM events GROUP BY 1) ON c_custkey = user_id")
def join_outer(spark, sf_dir):
    n = table(spark, sf_dir, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, sf_dir, "customer").select("c_custkey").join(n, F.col("c_custkey") == F.col("user_id"), "full").select("c_custkey", "user_id", F.coalesce("n", F.lit(0)).alias("n"))


@register("op_join_semi_anti", "SELECT (SELECT count(*) FROM customer WHERE c_custkey IN (SELECT user_id FROM events)) AS active, (SELECT count(*) FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)) AS idle")
def join_semi_anti(spark, sf_dir):
    people, users = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id")), table(spark, sf_dir, "events").select("user_id")
    count = lambda how, name: people.join(users, "user_id", how).agg(F.count(F.lit(1)).alias(name))
    return count("left_semi", "active").crossJoin(count("left_anti", "idle"))  # one row each


@register("op_join_lateral", f"SELECT user_id, event_id, nth FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY t DESC, event_id) AS nth FROM {_E}) WHERE nth <= 3")
def join_lateral(spark, sf_dir):
    return O.top_per_group(_ev(spark, sf_dir), ["user_id"], [F.desc("t"), F.col("event_id")], 3).select("user_id", "event_id", F.col("nth").cast("bigint").alias("nth"))


@register("op_agg_basic", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, round(avg(value), 6) AS mean, min(value) AS low, max(value) AS high, arg_max(event_id, value) AS top, count(*) FILTER (value > 50) AS large, bool_or(value > 99) AS any_99, round(stddev_samp(value), 6) AS deviation FROM events GROUP BY 1")
def agg_basic(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("low"), F.max("value").alias("high"),
        F.max_by("event_id", "value").alias("top"), F.count_if(F.col("value") > 50).alias("large"), F.bool_or(F.col("value") > 99).alias("any_99"), F.round(F.stddev_samp("value"), 6).alias("deviation"),
    )


@register("op_agg_distinct", f"SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT k) AS ks FROM {_E} GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return _ev(spark, sf_dir).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("k").alias("ks"))


@register("op_agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS middle, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("middle"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@register("op_agg_cube", f"SELECT event_type, user_id % 3 AS host, count(*) AS n, grouping(event_type) * 2 + grouping(user_id % 3) AS g FROM {_E} GROUP BY CUBE (event_type, user_id % 3)")
def agg_cube(spark, sf_dir):
    e = _ev(spark, sf_dir).withColumn("host", F.col("user_id") % 3)
    return e.cube("event_type", "host").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))


@register("op_agg_rollup", f"SELECT event_type, user_id % 3 AS host, count(*) AS n FROM {_E} GROUP BY ROLLUP (event_type, user_id % 3)")
def agg_rollup(spark, sf_dir):
    return _ev(spark, sf_dir).withColumn("host", F.col("user_id") % 3).rollup("event_type", "host").agg(F.count(F.lit(1)).alias("n"))


@register("op_agg_grouping_sets", f"SELECT event_type, k, count(*) AS n FROM {_E} GROUP BY GROUPING SETS ((event_type), (k), ())")
def agg_grouping_sets(spark, sf_dir):
    e = _ev(spark, sf_dir)
    return e.groupingSets([[e.event_type], [e.k], []], e.event_type, e.k).agg(F.count(F.lit(1)).alias("n"))


@register("op_agg_pivot", f"SELECT user_id % 3 AS host, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'error') AS error FROM {_E} GROUP BY 1")
def agg_pivot(spark, sf_dir):
    return _ev(spark, sf_dir).withColumn("host", F.col("user_id") % 3).groupBy("host").pivot("event_type", ["view", "error"]).agg(F.count(F.lit(1))).fillna(0)


@register("op_agg_unpivot", "SELECT c_custkey, 'nation' AS what, CAST(c_nationkey AS DOUBLE) AS v FROM customer UNION ALL SELECT c_custkey, 'balance', c_acctbal FROM customer")
def agg_unpivot(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("double").alias("nation"), F.col("c_acctbal").alias("balance"))
    return c.unpivot("c_custkey", ["nation", "balance"], "what", "v")


@register("op_agg_sketch")
def agg_sketch(spark, sf_dir):
    """Distinct users by merged sketches, near the exact number."""
    return O.distinct_sketch(_ev(spark, sf_dir), ["event_type"], "user_id")


@register("op_window_ranking", f"SELECT event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY k) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY k) AS dr, ntile(4) OVER w AS quarter FROM {_E} WINDOW w AS (PARTITION BY user_id ORDER BY t, event_id)")
def window_ranking(spark, sf_dir):
    w, v = Window.partitionBy("user_id").orderBy("t", "event_id"), Window.partitionBy("user_id").orderBy("k")
    cols = {"rn": F.row_number().over(w), "rk": F.rank().over(v), "dr": F.dense_rank().over(v), "quarter": F.ntile(4).over(w)}
    return _ev(spark, sf_dir).select("event_id", *[c.cast("bigint").alias(n) for n, c in cols.items()])


@register("op_window_analytic", f"SELECT event_id, t - lag(t) OVER w AS gap, lead(event_id) OVER w AS next_id, first_value(event_id) OVER w AS first_id FROM {_E} WINDOW w AS (PARTITION BY user_id ORDER BY t, event_id)")
def window_analytic(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("t", "event_id")
    return _ev(spark, sf_dir).select("event_id", (F.col("t") - F.lag("t").over(w)).alias("gap"), F.lead("event_id").over(w).alias("next_id"), F.first("event_id").over(w).alias("first_id"))


@register("op_window_frames", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN {24 * _H} PRECEDING AND CURRENT ROW) AS last_day, count(*) OVER (PARTITION BY user_id ORDER BY t ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS last_four FROM {_E}")
def window_frames(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("t")
    return _ev(spark, sf_dir).select("event_id", F.count(F.lit(1)).over(w.rangeBetween(-24 * _H, 0)).alias("last_day"), F.count(F.lit(1)).over(w.rowsBetween(-3, 0)).alias("last_four"))


@register("op_window_sessions", f"SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS session FROM (SELECT user_id, t, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) > {12 * _H} THEN 1 ELSE 0 END AS new FROM {_E})) GROUP BY 1, 2".replace("sum(new) OVER (PARTITION BY user_id ORDER BY t) AS session", "CAST(sum(new) OVER (PARTITION BY user_id ORDER BY t) AS BIGINT) AS session"))
def window_sessions(spark, sf_dir):
    return O.sessions(_ev(spark, sf_dir), "user_id", "t", 12 * _H).groupBy("user_id", F.col("session").cast("bigint").alias("session")).agg(F.count(F.lit(1)).alias("n"))


@register("op_sort_limit", f"SELECT event_id, value FROM {_E} ORDER BY value DESC, event_id LIMIT 20 OFFSET 5")
def sort_limit(spark, sf_dir):
    return _ev(spark, sf_dir).orderBy(F.desc("value"), "event_id").offset(5).limit(20).select("event_id", "value")


@register("op_set_all", f"SELECT k FROM {_E} WHERE event_type = 'view' EXCEPT ALL SELECT k FROM {_E} WHERE event_type = 'click'")
def set_all(spark, sf_dir):
    e = _ev(spark, sf_dir)
    return e.where("event_type = 'view'").select("k").exceptAll(e.where("event_type = 'click'").select("k"))


@register("op_set_intersect", f"SELECT user_id, k FROM {_E} WHERE event_type = 'view' INTERSECT SELECT user_id, k FROM {_E} WHERE event_type = 'click'")
def set_intersect(spark, sf_dir):
    e = _ev(spark, sf_dir)
    return e.where("event_type = 'view'").select("user_id", "k").intersect(e.where("event_type = 'click'").select("user_id", "k"))


@register("op_filter_conditions", "SELECT p_partkey FROM part WHERE (p_name LIKE '%ring%' OR p_type IN ('PROMO', 'SMALL')) AND p_size BETWEEN 5 AND 30 AND NOT starts_with(p_name, 'red') AND p_brand IS NOT NULL")
def filter_conditions(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    return p.where((F.col("p_name").like("%ring%") | F.col("p_type").isin("PROMO", "SMALL")) & F.col("p_size").between(5, 30) & ~F.col("p_name").startswith("red") & F.col("p_brand").isNotNull()).select("p_partkey")


@register("op_fn_strings", "SELECT p_partkey, upper(p_name) AS up, length(p_name) AS n, replace(p_name, ' ', '_') AS snake, split_part(p_name, ' ', 2) AS second, regexp_extract(p_brand, '([0-9]+)', 1) AS brand_no, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, md5(p_name) AS digest, instr(p_name, 'i') AS at, translate(p_name, 'ae', 'AE') AS changed FROM part")
def fn_strings(spark, sf_dir):
    return table(spark, sf_dir, "part").select(
        "p_partkey", F.upper("p_name").alias("up"), F.length("p_name").cast("bigint").alias("n"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("snake"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("second"),
        F.regexp_extract("p_brand", "([0-9]+)", 1).alias("brand_no"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.md5("p_name").alias("digest"), F.instr("p_name", "i").cast("bigint").alias("at"), F.translate("p_name", "ae", "AE").alias("changed"),
    )


@register("op_fn_dates", "SELECT event_id, CAST(year(ts) AS INTEGER) AS y, CAST(hour(ts) AS INTEGER) AS h, CAST(ts AS DATE) - DATE '2024-01-01' AS days, epoch_us(date_trunc('hour', ts)) AS hour_us, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow FROM events")
def fn_dates(spark, sf_dir):
    ts = F.col("ts").cast("timestamp")
    return table(spark, sf_dir, "events").select(
        "event_id", F.year(ts).alias("y"), F.hour(ts).alias("h"), F.datediff(F.to_date(ts), F.lit("2024-01-01").cast("date")).cast("bigint").alias("days"), F.unix_micros(F.date_trunc("hour", ts)).alias("hour_us"), F.dayofweek(ts).alias("dow")
    )


@register("op_fn_math", "SELECT event_id, round(ln(1 + value), 8) AS l, round(sqrt(value), 8) AS s, greatest(value, 50.0) AS g, event_id % 7 AS m, sign(value - 50) AS sg, abs(value - 50) AS a FROM events".replace("sign(value - 50)", "CAST(sign(value - 50) AS DOUBLE)"))
def fn_math(spark, sf_dir):
    v = F.col("value")
    return table(spark, sf_dir, "events").select("event_id", F.round(F.log1p(v), 8).alias("l"), F.round(F.sqrt(v), 8).alias("s"), F.greatest(v, F.lit(50.0)).alias("g"), F.pmod("event_id", F.lit(7)).alias("m"), F.signum(v - 50).alias("sg"), F.abs(v - 50).alias("a"))


@register("op_fn_arrays", "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings")
def fn_arrays(spark, sf_dir):
    e = F.col("embedding")
    norm = F.aggregate(F.transform(e, lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x)
    return table(spark, sf_dir, "embeddings").select("vec_id", F.size(e).alias("n"), F.round(norm, 6).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@register("op_fn_explode", "SELECT l, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS l FROM part) GROUP BY 1")
def fn_explode(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.explode(F.split("p_name", " ")).alias("l")).groupBy("l").agg(F.count(F.lit(1)).alias("n"))


@register("op_fn_maps", "SELECT event_id, k AS value_k, CAST(1 AS INTEGER) AS entries FROM " + _E)
def fn_maps(spark, sf_dir):
    m = F.from_json("props", "map<string,bigint>")
    return table(spark, sf_dir, "events").select("event_id", F.element_at(m, "k").alias("value_k"), F.size(F.map_keys(m)).alias("entries"))


@register("op_fn_conditional", "SELECT event_id, CASE WHEN value > 90 THEN 'high' WHEN value > 10 THEN 'mid' ELSE 'low' END AS band, nullif(k, 0) AS k_or_null, coalesce(nullif(k, 0), -1) AS k_or_one FROM " + _E)
def fn_conditional(spark, sf_dir):
    v = F.col("value")
    return _ev(spark, sf_dir).select("event_id", F.when(v > 90, "high").when(v > 10, "mid").otherwise("low").alias("band"), F.nullif(F.col("k"), F.lit(0)).alias("k_or_null"), F.coalesce(F.nullif(F.col("k"), F.lit(0)), F.lit(-1)).alias("k_or_one"))


@register("op_fn_hash", "SELECT p_partkey, sha256(p_name) AS s FROM part")
def fn_hash(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.sha2("p_name", 256).alias("s"))


@register("op_sql_subqueries", "SELECT o_orderpriority, count(*) AS n FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R') AND o_totalprice > (SELECT avg(o_totalprice) FROM orders) GROUP BY 1 HAVING count(*) > 1")
def sql_subqueries(spark, sf_dir):
    table(spark, sf_dir, "orders").createOrReplaceTempView("sub_orders")
    table(spark, sf_dir, "lineitem").createOrReplaceTempView("sub_lineitem")
    return spark.sql(
        "SELECT o_orderpriority, count(*) AS n FROM sub_orders o WHERE EXISTS (SELECT 1 FROM sub_lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = :flag) "
        "AND o_totalprice > (SELECT avg(o_totalprice) FROM sub_orders) GROUP BY 1 HAVING count(*) > 1", args={"flag": "R"},
    )


@register("op_sql_pipe", "SELECT event_type, count(*) AS n FROM events WHERE value > 50 GROUP BY 1")
def sql_pipe(spark, sf_dir):
    table(spark, sf_dir, "events").createOrReplaceTempView("pipe_events")
    return spark.sql("FROM pipe_events |> WHERE value > 50 |> AGGREGATE count(*) AS n GROUP BY event_type")


@register("op_udf_pandas", "SELECT event_id, value * value + 1 AS v FROM events")
def udf_pandas(spark, sf_dir):
    @F.pandas_udf("double")
    def grow(x: pd.Series) -> pd.Series:
        return x * x + 1

    return table(spark, sf_dir, "events").select("event_id", grow("value").alias("v"))


@register("op_udf_grouped", "SELECT user_id, count(*) AS n, round(max(value) - min(value), 6) AS spread FROM events GROUP BY 1")
def udf_grouped(spark, sf_dir):
    def spread(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [pdf.user_id.iloc[0]], "n": [len(pdf)], "spread": [round(pdf.value.max() - pdf.value.min(), 6)]})

    return table(spark, sf_dir, "events").select("user_id", "value").groupBy("user_id").applyInPandas(spread, "user_id bigint, n bigint, spread double")


@register("op_join_lateral_sql", f"SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY t DESC, event_id) AS nth FROM {_E}) WHERE nth <= 3")
def join_lateral_sql(spark, sf_dir):
    """The last three events of each user, asked once per user."""
    _ev(spark, sf_dir).createOrReplaceTempView("lateral_events")
    return spark.sql(
        "SELECT u.user_id, l.event_id FROM (SELECT DISTINCT user_id FROM lateral_events) u, "
        # Not ORDER BY and LIMIT: correlated, they become a sort, a shuffle that loses its order, and row numbers without order.
        "LATERAL (SELECT event_id FROM (SELECT e.event_id, row_number() OVER (ORDER BY e.t DESC, e.event_id) AS nth FROM lateral_events e WHERE e.user_id <=> u.user_id) WHERE nth <= 3) l"
    )


@register("op_udtf", "SELECT p_partkey, CAST(generate_subscripts(w, 1) - 1 AS INTEGER) AS place, unnest(w) AS word FROM (SELECT p_partkey, string_split(p_name, ' ') AS w FROM part)")
def udtf(spark, sf_dir):
    """A table function of one row: the words of a name with their places."""

    class Words:
        def eval(self, name: str):
            yield from enumerate(name.split(" ") if name is not None else ())

    spark.udtf.register("name_words", F.udtf(Words, returnType="place int, word string"))
    table(spark, sf_dir, "part").createOrReplaceTempView("udtf_part")
    return spark.sql("SELECT p_partkey, w.place, w.word FROM udtf_part, LATERAL name_words(p_name) w")


@register("op_udf_sql", "SELECT l_orderkey, CAST(sum(CAST(floor(l_extendedprice * (1 - l_discount) * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem GROUP BY 1")
def udf_sql(spark, sf_dir):
    """A function defined in SQL, which the optimiser writes into the plan."""
    table(spark, sf_dir, "lineitem").createOrReplaceTempView("udf_lineitem")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION net_cents(price DOUBLE, discount DOUBLE) RETURNS BIGINT RETURN CAST(floor(price * (1 - discount) * 100) AS BIGINT)")
    return spark.sql("SELECT l_orderkey, sum(net_cents(l_extendedprice, l_discount)) AS cents FROM udf_lineitem GROUP BY 1")


@register("op_sample_stratified")
def sample_stratified(spark, sf_dir):
    """A share of each kind of event, the same on every run."""
    return table(spark, sf_dir, "events").sampleBy("event_type", {"view": 0.1, "error": 0.2}, seed=3).select("event_id", "event_type")
