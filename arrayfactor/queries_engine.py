"""Queries on joins, aggregation, windows, sets, functions, sources, streams and user functions, with their SQL."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workloads as w
from .functions.hashing import keyed, uniform, uniform_sql
from .functions.normal import cdf
from .operators import arrays, sampling
from .queries_arrays import _DEL, ENC, _factors_and_deltas
from .sources import coo
from .sources.tables import checkpointed, scratch, table
from .streaming import events as st

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    def add(f):
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


# ---- joins

_BRAND = "SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS s FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"


def _brands(spark: SparkSession, sf: str, hint: str) -> DataFrame:
    part = table(spark, sf, "part").select("p_partkey", "p_brand").hint(hint)
    lines = table(spark, sf, "lineitem").select("l_partkey", "l_quantity")
    return lines.join(part, lines.l_partkey == part.p_partkey).groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"))


@query("join_broadcast", _BRAND)
def join_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    return _brands(spark, sf, "broadcast")


@query("join_merge", _BRAND)
def join_merge(spark: SparkSession, sf: str) -> DataFrame:
    return _brands(spark, sf, "merge")


_BINS = [(0, 0, 20), (1, 20, 45), (2, 45, 80), (3, 80, 100)]
_BIN_SQL = "(VALUES " + ", ".join(map(str, _BINS)) + ") b(bin, lo, hi)"


@query("join_theta", f"SELECT bin, count(*) AS n FROM events JOIN {_BIN_SQL} ON (props->>'$.k')::INT >= lo AND (props->>'$.k')::INT < hi GROUP BY bin")
def join_theta(spark: SparkSession, sf: str) -> DataFrame:
    """A condition without equality against four literal rows."""
    bins = F.broadcast(spark.createDataFrame(_BINS, "bin int, lo int, hi int"))
    rows = w.log_records(spark, sf).select(F.col("k").cast("int").alias("k"))
    return rows.join(bins, (F.col("k") >= F.col("lo")) & (F.col("k") < F.col("hi"))).groupBy("bin").agg(F.count("*").alias("n"))


@query("join_range", f"SELECT bin, count(*) AS n FROM events JOIN {_BIN_SQL} ON (props->>'$.k')::INT >= lo AND (props->>'$.k')::INT < hi GROUP BY bin")
def join_range(spark: SparkSession, sf: str) -> DataFrame:
    """The same as an equi-join: every range is listed under each bucket of ten that it meets."""
    bins = spark.createDataFrame(_BINS, "bin int, lo int, hi int").withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / 10), F.floor((F.col("hi") - 1) / 10))))
    rows = w.log_records(spark, sf).select(F.col("k").cast("int").alias("k")).withColumn("bucket", F.floor(F.col("k") / 10))
    return rows.join(bins, "bucket").filter("k >= lo AND k < hi").groupBy("bin").agg(F.count("*").alias("n"))


@query("join_asof", "SELECT event_id, max_by(p, (pts, p)) AS prev_purchase_id FROM (SELECT e.event_id, x.event_id AS p, x.ts AS pts FROM events e LEFT JOIN events x ON x.user_id = e.user_id AND x.event_type = 'purchase' AND x.ts <= e.ts) GROUP BY event_id")
def join_asof(spark: SparkSession, sf: str) -> DataFrame:
    """Each event with its user's latest purchase at or before it; one window, no pairs."""
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", F.col("event_id").alias("id")))
    latest = F.max(bought).over(Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow))
    rows = w.log_records(spark, sf).withColumn("ts", F.unix_micros(F.col("ts").cast("timestamp")))
    return rows.select("event_id", latest.alias("x")).select("event_id", F.col("x.id").alias("prev_purchase_id"))


@query("join_interval", "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")
def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    """A click and a purchase of one user within the hour; times meet by hour buckets, so that pairs stay local."""
    rows = w.log_records(spark, sf).select("user_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).withColumn("hour", F.floor(F.unix_seconds("ts") / 3600))
    click = rows.filter("event_type = 'click'").select("user_id", F.col("ts").alias("t0"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    buy = rows.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("t1"), "hour")
    met = click.join(buy, ["user_id", "hour"]).filter((F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr("INTERVAL 1 HOUR")))
    return met.groupBy("user_id").agg(F.count("*").alias("pairs"))


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    urgent = table(spark, sf, "orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf, "customer").select("c_custkey").join(urgent, "c_custkey", "left_semi")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    urgent = table(spark, sf, "orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf, "customer").select("c_custkey").join(urgent, "c_custkey", "left_anti")


@query("join_full", "SELECT nation, c, s FROM (SELECT c_nationkey AS nation, count(*) AS c FROM customer WHERE c_acctbal > 5000 GROUP BY 1) FULL JOIN (SELECT s_nationkey AS nation, count(*) AS s FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) USING (nation)")
def join_full(spark: SparkSession, sf: str) -> DataFrame:
    c = table(spark, sf, "customer").filter("c_acctbal > 5000").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("c"))
    s = table(spark, sf, "supplier").filter("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("s"))
    return c.join(s, "nation", "full").select("nation", "c", "s")


# ---- aggregation

_MEASURES = "count(*) AS n, round(sum(l_quantity), 2) AS q"


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity")


def _measured(grouped, *more) -> DataFrame:
    return grouped.agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"), *more)


_G = "(2 * grouping(l_returnflag) + grouping(l_linestatus))::BIGINT AS g"


@query("agg_rollup", f"SELECT l_returnflag, l_linestatus, {_G}, {_MEASURES} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _measured(_lines(spark, sf).rollup("l_returnflag", "l_linestatus"))


@query("agg_cube", f"SELECT l_returnflag, l_linestatus, {_G}, {_MEASURES} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _measured(_lines(spark, sf).cube("l_returnflag", "l_linestatus"))


@query("agg_grouping_sets", f"SELECT l_returnflag, l_linestatus, {_G}, {_MEASURES} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
def agg_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _measured(_lines(spark, sf).groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT props) AS props FROM events GROUP BY event_type")
def agg_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("props").alias("props"))


@query("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
def agg_percentile(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("value", F.lit(0.9)), 6).alias("p90"))


@query("agg_approx")
def agg_approx(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("p50"), F.max_by("event_id", "value").alias("largest"), F.corr("value", "user_id").alias("r"))


# ---- windows, sorting, sets


@query("win_rank", ENC + " SELECT mode, idx, rank() OVER o AS r, dense_rank() OVER o AS d, round(percent_rank() OVER o, 6) AS p, round(cume_dist() OVER o, 6) AS c FROM sw WINDOW o AS (PARTITION BY mode ORDER BY weight DESC)")
def win_rank(spark: SparkSession, sf: str) -> DataFrame:
    o = Window.partitionBy("mode").orderBy(F.desc("weight"))
    return arrays.slice_weights(w.encoded_log(spark, sf)).select("mode", "idx", F.rank().over(o).cast("long").alias("r"), F.dense_rank().over(o).cast("long").alias("d"), F.round(F.percent_rank().over(o), 6).alias("p"), F.round(F.cume_dist().over(o), 6).alias("c"))


@query("win_ntile_grid", ENC + " SELECT mode, idx, ntile(4) OVER (PARTITION BY mode ORDER BY md5(mode || ':' || idx), idx) AS segment FROM sw")
def win_ntile_grid(spark: SparkSession, sf: str) -> DataFrame:
    o = Window.partitionBy("mode").orderBy(F.md5(keyed(F.col("mode"), F.col("idx")).cast("binary")), "idx")
    return arrays.slice_weights(w.encoded_log(spark, sf)).select("mode", "idx", F.ntile(4).over(o).cast("long").alias("segment"))


@query("win_cumweight", ENC + " SELECT mode, idx, sum(weight) OVER (PARTITION BY mode ORDER BY idx)::BIGINT AS upto FROM sw")
def win_cumweight(spark: SparkSession, sf: str) -> DataFrame:
    o = Window.partitionBy("mode").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return arrays.slice_weights(w.encoded_log(spark, sf)).select("mode", "idx", F.sum("weight").over(o).alias("upto"))


@query("win_lead_duration", "SELECT event_id, (epoch_us(lead(ts) OVER o) - epoch_us(ts)) // 1000000 AS seconds FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lead_duration(spark: SparkSession, sf: str) -> DataFrame:
    o = Window.partitionBy("user_id").orderBy("ts", "event_id")
    micros = lambda c: F.unix_micros(c.cast("timestamp"))
    rows = w.log_records(spark, sf)
    return rows.select("event_id", F.floor((micros(F.lead("ts").over(o)) - micros(F.col("ts"))) / 1_000_000).alias("seconds"))


@query("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_frame(spark: SparkSession, sf: str) -> DataFrame:
    rows = w.log_records(spark, sf).withColumn("s", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000))
    return rows.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("n"))


@query("topk_global", ENC + " SELECT mode, idx, weight FROM sw ORDER BY weight DESC, mode, idx LIMIT 10")
def topk_global(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.slice_weights(w.encoded_log(spark, sf)).orderBy(F.desc("weight"), "mode", "idx").limit(10)


@query("topk_per_mode", ENC + " SELECT mode, idx, weight FROM (SELECT *, row_number() OVER (PARTITION BY mode ORDER BY weight DESC, idx) AS n FROM sw) WHERE n <= 3")
def topk_per_mode(spark: SparkSession, sf: str) -> DataFrame:
    n = F.row_number().over(Window.partitionBy("mode").orderBy(F.desc("weight"), "idx"))
    return arrays.slice_weights(w.encoded_log(spark, sf)).withColumn("n", n).filter("n <= 3").drop("n")


_SETS = "(SELECT DISTINCT user_id, event_type FROM events WHERE ts < TIMESTAMP '2024-01-16') {0} (SELECT DISTINCT user_id, event_type FROM events WHERE ts >= TIMESTAMP '2024-01-10')"


def _halves(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    rows = w.log_records(spark, sf)
    return (rows.filter("ts < timestamp_ntz'2024-01-16'").select("user_id", "event_type").distinct(), rows.filter("ts >= timestamp_ntz'2024-01-10'").select("user_id", "event_type").distinct())


@query("set_union", _SETS.format("UNION ALL"))
def set_union(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _halves(spark, sf)
    return a.unionByName(b)


@query("set_intersect", _SETS.format("INTERSECT"))
def set_intersect(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _halves(spark, sf)
    return a.intersect(b)


@query("set_except", _SETS.format("EXCEPT"))
def set_except(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _halves(spark, sf)
    return a.exceptAll(b)


# ---- scalar functions


@query("fn_string", "SELECT c_custkey, lower(c_name) AS l, split_part(c_name, '#', 1) AS head, regexp_extract(c_name, '([0-9]+)', 1) AS digits, c_mktsegment || '-' || c_nationkey AS tag, substr(md5(c_name), 1, 8) AS h FROM customer")
def fn_string(spark: SparkSession, sf: str) -> DataFrame:
    c = table(spark, sf, "customer")
    return c.select("c_custkey", F.lower("c_name").alias("l"), F.split_part("c_name", F.lit("#"), F.lit(1)).alias("head"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("digits"), F.concat_ws("-", "c_mktsegment", "c_nationkey").alias("tag"), F.substring(F.md5(F.col("c_name").cast("binary")), 1, 8).alias("h"))


@query("fn_date", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, year(o_orderdate)::BIGINT AS y, dayofyear(o_orderdate)::BIGINT AS d, strftime(o_orderdate + INTERVAL 30 DAY, '%Y-%m-%d') AS due, date_diff('day', TIMESTAMP '1990-01-01', date_trunc('day', o_orderdate)) AS age FROM orders")
def fn_date(spark: SparkSession, sf: str) -> DataFrame:
    day = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", day), "yyyy-MM-dd").alias("month"), F.year(day).cast("long").alias("y"), F.dayofyear(day).cast("long").alias("d"), F.date_format(day + F.expr("INTERVAL 30 DAY"), "yyyy-MM-dd").alias("due"), F.datediff(F.to_date(day), F.lit("1990-01-01").cast("date")).cast("long").alias("age"))


@query("fn_math", "SELECT event_id, round(exp(-value / 100), 6) AS e, round(ln(1 + abs(value)), 6) AS l, round(sqrt(abs(value)), 6) AS s, round(sin(value), 6) + 0.0 AS n, (user_id % 7)::BIGINT AS m FROM events")
def fn_math(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", F.round(F.exp(-v / 100), 6).alias("e"), F.round(F.log1p(F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), (F.round(F.sin(v), 6) + 0.0).alias("n"), F.pmod("user_id", F.lit(7)).cast("long").alias("m"))


@query("fn_array", "SELECT vec_id, len(embedding)::BIGINT AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, round(embedding[3]::DOUBLE, 6) AS third, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS pos FROM embeddings")
def fn_array(spark: SparkSession, sf: str) -> DataFrame:
    squares = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return table(spark, sf, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(squares, 5).alias("norm2"), F.round(F.element_at("embedding", 3).cast("double"), 6).alias("third"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"))


@query("fn_map", "SELECT p_partkey, p_size::BIGINT AS size, round(p_retailprice, 2) AS price, 2::BIGINT AS n FROM part")
def fn_map(spark: SparkSession, sf: str) -> DataFrame:
    pairs = F.create_map(F.lit("size"), F.col("p_size").cast("double"), F.lit("price"), F.col("p_retailprice"), F.lit("none"), F.lit(-1.0))
    kept = F.map_filter(pairs, lambda k, v: v >= 0)
    return table(spark, sf, "part").select("p_partkey", kept.alias("m")).select("p_partkey", F.col("m")["size"].cast("long").alias("size"), F.round(F.col("m")["price"], 2).alias("price"), F.size("m").cast("long").alias("n"))


@query("fn_json", "SELECT event_id, (props->>'$.k')::BIGINT AS k, '{\"u\":' || user_id || '}' AS j FROM events")
def fn_json(spark: SparkSession, sf: str) -> DataFrame:
    parsed = F.from_json("props", "k long")
    return table(spark, sf, "events").select("event_id", parsed["k"].alias("k"), F.to_json(F.struct(F.col("user_id").alias("u"))).alias("j"))


@query("fn_url", "SELECT page_id, regexp_extract(url, '^https?://([^/:?#]+)', 1) AS host, regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def fn_url(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "pages").select("page_id", F.coalesce(F.parse_url("url", F.lit("HOST")), F.lit("")).alias("host"), F.coalesce(F.parse_url("url", F.lit("PATH")), F.lit("")).alias("path"))


# ---- sources, sinks, SQL


@query("scan_prune", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_discount >= 0.09 AND l_quantity < 10 GROUP BY l_returnflag")
def scan_prune(spark: SparkSession, sf: str) -> DataFrame:
    """Three of eleven columns are read and both conditions reach the scan."""
    return table(spark, sf, "lineitem").filter("l_discount >= 0.09 AND l_quantity < 10").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("coo_roundtrip", ENC + " SELECT * FROM e")
def coo_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Written as coordinate text by the tasks and read again by Spark's text reader."""
    path = f"{scratch(spark)}/coo-{uuid.uuid4().hex[:12]}"
    w.encoded_log(spark, sf).select(F.concat_ws(" ", "i1", "i2", "i3", "y").alias("value")).write.text(path)
    return coo.read_coordinates(spark, path, 3)


@query("json_props", "SELECT (props->>'$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query("sql_facade", ENC + " SELECT i2, count(*) AS nnz, count(DISTINCT i1) AS users FROM e GROUP BY i2")
def sql_facade(spark: SparkSession, sf: str) -> DataFrame:
    w.encoded_log(spark, sf).createOrReplaceTempView("arr_log")
    return spark.sql("SELECT i2, count(*) AS nnz, count(DISTINCT i1) AS users FROM arr_log GROUP BY i2")


# ---- streams


def _stamp(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("st_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def st_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return _stamp(st.replayed(st.tumbling(st.event_stream(spark, sf)), "complete")).withColumn("total", F.round("total", 4))


@query("st_sliding", "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([b, b - INTERVAL 12 HOUR]) AS s FROM (SELECT event_type, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '2000-01-01') AS b FROM events)) GROUP BY ALL")
def st_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return _stamp(st.replayed(st.sliding(st.event_stream(spark, sf)), "complete"))


@query("st_session", "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def st_session(spark: SparkSession, sf: str) -> DataFrame:
    return _stamp(st.replayed(st.sessions(st.event_stream(spark, sf)), "complete"))


@query("st_dedup_array", "SELECT DISTINCT user_id, event_type, 1.0::DOUBLE AS y FROM events")
def st_dedup_array(spark: SparkSession, sf: str) -> DataFrame:
    return st.replayed(st.presence(st.event_stream(spark, sf), ["user_id", "event_type"]))


@query("st_static_encode", ENC + " SELECT event_id, d2.idx FROM events JOIN d2 ON event_type = d2.key")
def st_static_encode(spark: SparkSession, sf: str) -> DataFrame:
    dictionary = checkpointed(arrays.mode_dictionary(w.log_array(spark, sf), w.LOG), "dictionary")
    return st.replayed(st.static_encode(st.event_stream(spark, sf).select("event_id", "event_type"), dictionary, "event_type", 2)).select("event_id", "idx")


@query("st_user_state", "SELECT user_id, count(*) AS weight FROM events GROUP BY user_id")
def st_user_state(spark: SparkSession, sf: str) -> DataFrame:
    return st.replayed(st.user_weights(st.event_stream(spark, sf)), "update").groupBy("user_id").agg(F.max("weight").alias("weight"))


# ---- user functions


@query("udaf_vec_mean", ENC + f", {_DEL} SELECT mode::INT AS mode, idx, d::INT AS d, round(avg(v), 6) + 0.0 AS value FROM dl GROUP BY ALL")
def udaf_vec_mean(spark: SparkSession, sf: str) -> DataFrame:
    """A grouped-aggregate user function over vector components."""

    @F.pandas_udf("double")
    def vec_mean(v: pd.Series) -> float:
        return float(v.mean())

    deltas = _factors_and_deltas(spark, sf)[1].select("mode", "idx", F.posexplode("delta").alias("d", "v"))
    return deltas.groupBy("mode", "idx", "d").agg((F.round(vec_mean("v"), 6) + F.lit(0.0)).alias("value"))


@query("udtf_plan")
def udtf_plan(spark: SparkSession, sf: str) -> DataFrame:
    """A table function that draws uniform subarrays of a mode, registered for SQL and applied to the modes of the access log."""

    @F.udtf(returnType="sub_id: bigint, pos: int, idx: bigint")
    class SubarrayPlan:
        def eval(self, mode: int, size: int, side: int, count: int, seed: int):
            for sub in range(count):
                for p, i in enumerate(sorted(sampling._draw(seed, sub, mode).permutation(size)[:side]), 1):
                    yield sub, p, int(i) + 1

    spark.udtf.register("subarray_plan", SubarrayPlan)
    arrays.slice_weights(w.encoded_log(spark, sf)).groupBy("mode").agg(F.max("idx").alias("size")).createOrReplaceTempView("log_modes")
    return spark.sql("SELECT p.sub_id, m.mode, p.pos, p.idx FROM log_modes m, LATERAL subarray_plan(m.mode, m.size, 5, 4, 9) p")


@query("udf_probit")
def udf_probit(spark: SparkSession, sf: str) -> DataFrame:
    """The normal distribution function as a vectorised user function."""

    @F.pandas_udf("double")
    def probit_cdf(x: pd.Series) -> pd.Series:
        return pd.Series(cdf(x.to_numpy()))

    return table(spark, sf, "events").select("event_id", probit_cdf((F.col("value") - 50) / 25).alias("p"))


@query("hash_uniform", f"SELECT event_id, {uniform_sql(chr(39) + 'a:' + chr(39) + ' || event_id')} AS u FROM events")
def hash_uniform(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_id", uniform(keyed("a", F.col("event_id"))).alias("u"))
