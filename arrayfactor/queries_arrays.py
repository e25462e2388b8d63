"""Queries on arrays, sampling, merging, baselines' products, measures and protocol, with their SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as w
from .functions.hashing import keyed, uniform, uniform_sql
from .functions.kernels import Kernel, kernel_table
from .operators import arrays, baselines, measures, predict, sampling, train
from .plans import cost, protocol
from .sources.tables import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    def add(f):
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


def num(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    """Columns rounded, without negative zeros."""
    return df.withColumns({c: F.round(c, digits) + F.lit(0.0) for c in columns})


TOK = f"list_filter(regexp_split_to_array(lower(text), '{w.TOKEN}'), lambda x: x <> '')"
TRIPLES = """
t AS MATERIALIZED (SELECT doc_id, {tok} AS w FROM documents),
f AS MATERIALIZED (SELECT u FROM (SELECT u, count(*) AS c FROM (SELECT unnest(w) AS u FROM t) GROUP BY u ORDER BY c DESC, u LIMIT {top})),
g AS MATERIALIZED (SELECT doc_id, w[i] AS w1, w[i + 1] AS w2, w[i + 2] AS w3 FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM t)),
r AS MATERIALIZED (SELECT w1, w2, w3, count(*)::BIGINT AS n FROM g WHERE w1 IN (SELECT u FROM f) AND w2 IN (SELECT u FROM f) AND w3 IN (SELECT u FROM f){more} GROUP BY ALL)"""
TR = TRIPLES.format(tok=TOK, top=200, more="")
LOG = "log AS MATERIALIZED (SELECT DISTINCT user_id, event_type, props->>'$.k' AS k FROM events)"
ENC = (
    "WITH "
    + LOG
    + ", "
    + ", ".join(f"d{n} AS MATERIALIZED (SELECT c AS key, row_number() OVER (ORDER BY md5(c), c) AS idx, weight FROM (SELECT {c}::VARCHAR AS c, count(*) AS weight FROM log GROUP BY 1))" for n, c in enumerate(w.LOG, 1))
    + ", e AS MATERIALIZED (SELECT d1.idx AS i1, d2.idx AS i2, d3.idx AS i3, 1.0::DOUBLE AS y FROM log JOIN d1 ON user_id::VARCHAR = d1.key JOIN d2 ON event_type = d2.key JOIN d3 ON k = d3.key)"
    + ", m AS MATERIALIZED (SELECT max(i1) AS m1, max(i2) AS m2, max(i3) AS m3 FROM e)"
    + ", sw AS MATERIALIZED (SELECT 1 AS mode, i1 AS idx, count(*) AS weight FROM e GROUP BY i1 UNION ALL SELECT 2, i2, count(*) FROM e GROUP BY i2 UNION ALL SELECT 3, i3, count(*) FROM e GROUP BY i3)"
)


def U(*parts: str) -> str:
    return uniform_sql(" || ':' || ".join(f"({p})::VARCHAR" for p in parts))


# ---- arrays


@query("triple_array", f"WITH {TR} SELECT * FROM r")
def triple_array(spark: SparkSession, sf: str) -> DataFrame:
    return w.triple_counts(spark, sf)


@query("confidence_filter", f"WITH {TR} SELECT * FROM r WHERE n >= 2")
def confidence_filter(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.filter_confidence(w.triple_counts(spark, sf), "n", 2)


@query("quality_triples", f"WITH {TRIPLES.format(tok=TOK, top=200, more=' AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)')} SELECT * FROM r")
def quality_triples(spark: SparkSession, sf: str) -> DataFrame:
    return w.triple_counts(spark, sf, quality=True)


@query("log_array", f"WITH {LOG} SELECT user_id, event_type, k, 1.0::DOUBLE AS y FROM log")
def log_array(spark: SparkSession, sf: str) -> DataFrame:
    return w.log_array(spark, sf)


@query("order_array", "SELECT DISTINCT o_custkey, l_partkey, l_suppkey, 1.0::DOUBLE AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def order_array(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.build_array(w.order_lines(spark, sf), ["o_custkey", "l_partkey", "l_suppkey"])


@query("order_month_array", "SELECT DISTINCT o_custkey, l_suppkey, strftime(l_shipdate, '%Y-%m') AS month, 1.0::DOUBLE AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def order_month_array(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.build_array(w.order_lines(spark, sf).withColumn("month", F.date_format("l_shipdate", "yyyy-MM")), ["o_custkey", "l_suppkey", "month"])


NATION = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"


@query("nation_4way", f"SELECT DISTINCT c_nationkey, p_brand, p_type, s_nationkey, 1.0::DOUBLE AS y {NATION} WHERE l_returnflag = 'R' AND l_discount >= 0.09 AND o_orderpriority = '1-URGENT'")
def nation_4way(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.build_array(w.nation_records(spark, sf), ["c_nationkey", "p_brand", "p_type", "s_nationkey"])


@query("trade_sum", "SELECT c_nationkey AS nation, p_brand AS brand, strftime(l_shipdate, '%Y-%m') AS month, round(ln(1 + sum(l_extendedprice)), 6) AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def trade_sum(spark: SparkSession, sf: str) -> DataFrame:
    arr = arrays.build_array(w.trade_records(spark, sf), ["nation", "brand", "month"], "sum", "l_extendedprice")
    return arr.withColumn("y", F.round(F.log1p("y"), 6))


@query("trade_count", "SELECT c_nationkey AS nation, p_brand AS brand, strftime(l_shipdate, '%Y-%m') AS month, count(*)::DOUBLE AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def trade_count(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.build_array(w.trade_records(spark, sf), ["nation", "brand", "month"], "count")


def _word_array(rows: DataFrame, keys: list[str], top: int | None) -> DataFrame:
    words = rows.withColumn("w", w.tokens(F.col("text")))
    long = words.select(*keys, F.explode("w").alias("token"))
    if top:
        long = long.join(F.broadcast(w.top_tokens(words, top)), F.col("token") == F.col("t"), "left_semi")
    return arrays.build_array(long, [*keys, "token"], "count")


def _word_sql(source: str, keys: str, top: int | None) -> str:
    where = f" WHERE token IN (SELECT token FROM (SELECT token, count(*) AS c FROM l GROUP BY token ORDER BY c DESC, token LIMIT {top}))" if top else ""
    return f"WITH l AS MATERIALIZED (SELECT {keys}, unnest({TOK}) AS token FROM {source}) SELECT {keys}, token, count(*)::DOUBLE AS y FROM l{where} GROUP BY ALL"


@query("doc_keyword", _word_sql("documents", "doc_id, source", 124))
def doc_keyword(spark: SparkSession, sf: str) -> DataFrame:
    return _word_array(table(spark, sf, "documents").select("doc_id", "source", "text"), ["doc_id", "source"], 124)


@query("doc_keyword_4way", _word_sql("documents", "source, doc_id, lang", 330))
def doc_keyword_4way(spark: SparkSession, sf: str) -> DataFrame:
    return _word_array(table(spark, sf, "documents").select("doc_id", "source", "lang", "text"), ["source", "doc_id", "lang"], 330)


@query("chat_array", _word_sql("conversations", "conv_id, role", None))
def chat_array(spark: SparkSession, sf: str) -> DataFrame:
    return _word_array(table(spark, sf, "conversations").select("conv_id", "role", "text"), ["conv_id", "role"], None)


@query("page_array", "WITH l AS (SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, unnest(list_filter(regexp_split_to_array(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^a-zà-öø-ÿœæ]+'), lambda x: x <> '')) AS token FROM pages) SELECT host, token, count(*)::DOUBLE AS y FROM l GROUP BY ALL")
def page_array(spark: SparkSession, sf: str) -> DataFrame:
    pages = table(spark, sf, "pages").select(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return _word_array(pages, ["host"], None)


@query("mode_dict_log", ENC + " SELECT 1 AS mode, idx, key, weight FROM d1 UNION ALL SELECT 2, idx, key, weight FROM d2 UNION ALL SELECT 3, idx, key, weight FROM d3")
def mode_dict_log(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.mode_dictionary(w.log_array(spark, sf), w.LOG)


@query("encode_log", ENC + " SELECT * FROM e")
def encode_log(spark: SparkSession, sf: str) -> DataFrame:
    return w.encoded_log(spark, sf)


@query("decode_log", f"WITH {LOG} SELECT user_id::VARCHAR AS user_id, event_type, k, 1.0::DOUBLE AS y FROM log")
def decode_log(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.log_array(spark, sf)
    dictionary = arrays.mode_dictionary(arr, w.LOG)
    return arrays.decode(arrays.encode(arr, dictionary, w.LOG), dictionary, w.LOG)


POS = "((i1 - 1) * m2 * m3 + (i2 - 1) * m3 + i3)"


@query("linear_index", ENC + f" SELECT e.*, {POS}::BIGINT AS pos FROM e, m")
def linear_index(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return arrays.linear_index(arr, w.sizes_of(arr))


@query("from_linear", ENC + f" SELECT e.*, {POS}::BIGINT AS pos FROM e, m")
def from_linear(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    sizes = w.sizes_of(arr)
    return arrays.from_linear(arrays.linear_index(arr, sizes).select("pos", "y"), sizes)


for _k, _row, _col in ((1, "i1", "(i2 - 1) * m3 + i3"), (2, "i2", "(i1 - 1) * m3 + i3"), (3, "i3", "(i1 - 1) * m2 + i2")):

    @query(f"unfold_mode{_k}", ENC + f" SELECT {_row} AS row, ({_col})::BIGINT AS col, y FROM e, m")
    def unfold(spark: SparkSession, sf: str, k: int = _k) -> DataFrame:
        arr = w.stored_log(spark, sf)
        return arrays.unfold(arr, k, w.sizes_of(arr))


@query("mode_product", ENC + f", u AS (SELECT j, i1 AS i, {U('j', 'i1')} AS u FROM range(1, 4) t(j), (SELECT DISTINCT i1 FROM e)) SELECT j AS i1, i2, i3, round(sum(y * u), 6) + 0.0 AS y FROM e JOIN u ON i1 = i GROUP BY j, i2, i3")
def mode_product(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    matrix = spark.range(1, 4).toDF("j").join(spark.range(1, w.sizes_of(arr)[0] + 1).toDF("i"), F.lit(True)).withColumn("u", uniform(keyed(F.col("j"), F.col("i"))))
    return num(arrays.mode_product(arr, matrix, 1), "y")


def _fu(k: int, d: int, rank_seed: int = 11) -> str:
    return U(str(rank_seed), str(k), f"i{k}", str(d))


CORE = {(a, b, c): round(0.1 + 0.37 * a + 0.21 * b - 0.13 * c, 2) for a in range(2) for b in range(2) for c in range(2)}


@query("tucker_cells", ENC + " SELECT i1, i2, i3, round(" + " + ".join(f"({v}) * {_fu(1, a)} * {_fu(2, b)} * {_fu(3, c)}" for (a, b, c), v in CORE.items()) + ", 6) + 0.0 AS value FROM e")
def tucker_cells(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return num(arrays.tucker_cells(arr, CORE, baselines.random_factors(spark, w.sizes_of(arr), 2, 11)), "value")


@query("cp_cells", ENC + " SELECT i1, i2, i3, round(" + " + ".join(f"{_fu(1, d)} * {_fu(2, d)} * {_fu(3, d)}" for d in range(2)) + ", 6) + 0.0 AS value FROM e")
def cp_cells(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return num(arrays.cp_cells(arr, baselines.random_factors(spark, w.sizes_of(arr), 2, 11), 2), "value")


def _matrix(spark: SparkSession, sf: str, name: str, rows: str, cols: str) -> DataFrame:
    """(row, col, v): the shares of a table's records by two of its columns, whose values are numbered in their order."""
    counts = arrays.build_array(table(spark, sf, name), [rows, cols], "count")
    shares = counts.join(F.broadcast(counts.agg(F.sum("y").alias("all"))), F.lit(True)).withColumn("y", F.col("y") / F.col("all")).drop("all")
    return arrays.encode(shares, arrays.mode_dictionary(counts, [rows, cols], "key"), [rows, cols]).select(F.col("i1").alias("row"), F.col("i2").alias("col"), F.col("y").alias("v"))


_FLAGS, _STATES = ("lineitem", "l_returnflag", "l_linestatus"), ("orders", "o_orderpriority", "o_orderstatus")


def _matrix_sql(name: str, rows: str, cols: str) -> str:
    return f"SELECT dense_rank() OVER (ORDER BY r) AS row, dense_rank() OVER (ORDER BY c) AS col, n::DOUBLE / sum(n) OVER () AS v FROM (SELECT {rows} AS r, {cols} AS c, count(*) AS n FROM {name} WHERE {rows} IS NOT NULL AND {cols} IS NOT NULL GROUP BY ALL)"


MATRICES = f"WITH a AS MATERIALIZED ({_matrix_sql(*_FLAGS)}), b AS MATERIALIZED ({_matrix_sql(*_STATES)}), kr AS (SELECT (a.row - 1) * (SELECT max(row) FROM b) + b.row AS row, (a.col - 1) * (SELECT max(col) FROM b) + b.col AS col, a.v * b.v AS v FROM a, b)"


def _shape(m: DataFrame) -> list[int]:
    return [int(v) for v in m.agg(F.max("row"), F.max("col")).first()]


@query("kron_small", MATRICES + " SELECT row, col, round(v, 9) AS v FROM kr")
def kron_small(spark: SparkSession, sf: str) -> DataFrame:
    """Return flags by line states, times order priorities by order states."""
    a, b = _matrix(spark, sf, *_FLAGS), _matrix(spark, sf, *_STATES)
    return num(arrays.kron(a, b, *_shape(b)), "v", digits=9)


@query("vec_identity", MATRICES + " SELECT (SELECT max(row) FROM kr)::BIGINT AS n, 0.0::DOUBLE AS gap")
def vec_identity(spark: SparkSession, sf: str) -> DataFrame:
    """Stacked Tucker product against the Kronecker matrix times the stacked core; the core has a hashed weight for each pair of columns."""
    a, b = _matrix(spark, sf, *_FLAGS), _matrix(spark, sf, *_STATES)
    (rows_a, cols_a), (rows_b, cols_b) = _shape(a), _shape(b)
    core = spark.range(1, cols_a + 1).toDF("i1").join(spark.range(1, cols_b + 1).toDF("i2"), F.lit(True)).withColumn("y", uniform(keyed("w", F.col("i1"), F.col("i2"))))
    as_matrix = lambda m: m.select(F.col("row").alias("j"), F.col("col").alias("i"), F.col("v").alias("u"))
    product = arrays.linear_index(arrays.mode_product(arrays.mode_product(core, as_matrix(a), 1), as_matrix(b), 2), [rows_a, rows_b]).select(F.col("pos").alias("row"), "y")
    stacked = arrays.linear_index(core, [cols_a, cols_b]).select(F.col("pos").alias("col"), "y")
    other = arrays.kron(a, b, rows_b, cols_b).join(stacked, "col").groupBy("row").agg(F.sum(F.col("v") * F.col("y")).alias("z"))
    return product.join(other, "row", "full").agg(F.count("*").alias("n"), (F.round(F.max(F.abs(F.coalesce("y", F.lit(9.0)) - F.coalesce("z", F.lit(0.0)))), 9) + 0.0).alias("gap"))


@query("frobenius", f"WITH {TR} SELECT round(sqrt(sum(n::DOUBLE * n)), 6) AS norm FROM r")
def frobenius(spark: SparkSession, sf: str) -> DataFrame:
    return num(arrays.frobenius(w.triple_counts(spark, sf).select(F.col("n").cast("double").alias("y"))), "norm")


@query("inner_product", ENC + f", b AS (SELECT i1, i2, i3, {U('i1', 'i2', 'i3')} AS z FROM e) SELECT round(sum(y * z), 4) AS inner FROM e JOIN b USING (i1, i2, i3)".replace("AS inner", 'AS "inner"'))
def inner_product(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    other = arr.withColumn("y", uniform(keyed(F.col("i1"), F.col("i2"), F.col("i3"))))
    return num(arrays.inner(arr, other), "inner", digits=4)


def _stats_sql(name: str, source: str, modes: list[str]) -> str:
    m = [f"count(DISTINCT {c})" for c in modes]
    cells = " * ".join(f"{x}::DOUBLE" for x in m)
    return f"SELECT '{name}' AS name, " + ", ".join(f"{m[k] if k < len(m) else 'NULL::BIGINT'} AS m{k + 1}" for k in range(4)) + f", {cells} AS cells, count(*) AS nnz, round(100 * count(*) / ({cells}), 6) AS density_pct FROM ({source})"


_STATS = [("log", "log_array", list(w.LOG)), ("orders", "order_array", ["o_custkey", "l_partkey", "l_suppkey"]), ("mail", "order_month_array", ["o_custkey", "l_suppkey", "month"]), ("trade4", "nation_4way", ["c_nationkey", "p_brand", "p_type", "s_nationkey"]), ("triples", "triple_array", ["w1", "w2", "w3"]), ("doc_kw", "doc_keyword", ["doc_id", "token", "source"])]


@query("array_stats", " UNION ALL ".join(_stats_sql(n, ORACLES[q], m) for n, q, m in _STATS))
def array_stats(spark: SparkSession, sf: str) -> DataFrame:
    parts = [arrays.array_stats(QUERIES[q](spark, sf), m, n) for n, q, m in _STATS]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


_SIZES = "SELECT name, m1::DOUBLE AS m1, m2::DOUBLE AS m2, m3::DOUBLE AS m3, cells, nnz FROM (" + " UNION ALL ".join(_stats_sql(n, ORACLES[q], m) for n, q, m in _STATS[:2]) + ")"


def _sizes(spark: SparkSession, sf: str) -> DataFrame:
    """Sides, cells and nonzeros of the two large arrays, the access log and the orders."""
    parts = [arrays.array_stats(QUERIES[q](spark, sf), m, n) for n, q, m in _STATS[:2]]
    return parts[0].unionByName(parts[1]).select("name", *[F.col(f"m{k}").cast("double").alias(f"m{k}") for k in (1, 2, 3)], "cells", "nnz")


@query("slice_weights", ENC + " SELECT * FROM sw")
def slice_weights(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.slice_weights(w.stored_log(spark, sf))


@query("slice_weights_gs", ENC + " SELECT * FROM sw")
def slice_weights_gs(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.slice_weights_by_sets(w.stored_log(spark, sf))


@query("top_users_array", f"WITH {LOG} SELECT user_id, event_type, k, 1.0::DOUBLE AS y FROM log WHERE user_id IN (SELECT user_id FROM (SELECT user_id, count(*) AS c FROM log GROUP BY user_id ORDER BY c DESC, user_id LIMIT 50))")
def top_users_array(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.restrict_top(w.log_array(spark, sf), "user_id", 50)


@query("top_entities_array", f"WITH {TRIPLES.format(tok=TOK, top=100, more='')} SELECT * FROM r")
def top_entities_array(spark: SparkSession, sf: str) -> DataFrame:
    return w.triple_counts(spark, sf, top=100)


@query("permute_modes", ENC + "".join(f", p{k} AS (SELECT i{k} AS old, row_number() OVER (ORDER BY md5('5:{k}:' || i{k}), i{k}) AS n{k} FROM (SELECT DISTINCT i{k} FROM e))" for k in (1, 2, 3)) + " SELECT n1 AS i1, n2 AS i2, n3 AS i3, y FROM e JOIN p1 ON i1 = p1.old JOIN p2 ON i2 = p2.old JOIN p3 ON i3 = p3.old")
def permute_modes(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.permute_modes(w.stored_log(spark, sf), 5)


# ---- kernels

_D2 = "(list_sum(list_transform(range(1, 65), lambda i: (x[i]::DOUBLE - z[i]::DOUBLE) * (x[i]::DOUBLE - z[i]::DOUBLE))) / 64)"
_DOT = "list_sum(list_transform(range(1, 65), lambda i: x[i]::DOUBLE * z[i]::DOUBLE))"
_PAIRS = "WITH v AS (SELECT vec_id, embedding AS x FROM embeddings), p AS (SELECT l.vec_id AS a, r.vec_id AS b, l.x AS x, r.x AS z FROM v l, v r WHERE l.vec_id % 100 = 0)"
for _name, _kernel, _expr in (
    ("rbf", Kernel("rbf", scale=8.0), f"exp(-{_D2} / 2)"),
    ("linear", Kernel("linear", offset=1.0), f"{_DOT} + 1"),
    ("poly", Kernel("poly", gamma=1 / 64, offset=1.0, power=2), f"pow({_DOT} / 64 + 1, 2)"),
    ("matern32", Kernel("matern32", scale=8.0), f"(1 + sqrt(3) * sqrt({_D2})) * exp(-sqrt(3) * sqrt({_D2}))"),
    ("matern52", Kernel("matern52", scale=8.0), f"(1 + sqrt(5) * sqrt({_D2}) + 5 * {_D2} / 3) * exp(-sqrt(5) * sqrt({_D2}))"),
):

    @query(f"kernel_{_name}", f"{_PAIRS} SELECT a, b, round({_expr}, 6) + 0.0 AS k FROM p")
    def kernel_query(spark: SparkSession, sf: str, kernel: Kernel = _kernel) -> DataFrame:
        """The stated queries (ids divisible by 100) against all vectors."""
        vectors = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
        return num(kernel_table(vectors, kernel, vectors.filter("id % 100 = 0")), "k")


# ---- sampling

SIDES = [10, 3, 10]
_LIMIT = "CASE mode WHEN 2 THEN 3 ELSE 10 END"
PLAN = ENC + f", pl AS MATERIALIZED (SELECT sub_id, mode, pos, idx FROM (SELECT sub_id, mode, idx, row_number() OVER (PARTITION BY sub_id, mode ORDER BY {U('9', 'sub_id', 'mode', 'idx')}, idx) AS pos FROM sw, range(4) s(sub_id)) WHERE pos <= {_LIMIT})"
PLACES = ", x AS MATERIALIZED (SELECT a.sub_id, ((a.pos - 1) * 3 + (b.pos - 1)) * 10 + (c.pos - 1) AS lin, y FROM e JOIN pl a ON a.mode = 1 AND a.idx = i1 JOIN pl b ON b.mode = 2 AND b.idx = i2 AND b.sub_id = a.sub_id JOIN pl c ON c.mode = 3 AND c.idx = i3 AND c.sub_id = a.sub_id)"


def _plan(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    arr = w.stored_log(spark, sf)
    return arr, sampling.sample_by_hash(arrays.slice_weights(arr), 4, SIDES, 9)


@query("sample_uniform", PLAN + " SELECT * FROM pl")
def sample_uniform(spark: SparkSession, sf: str) -> DataFrame:
    return _plan(spark, sf)[1]


@query("sample_weighted", ENC + f" SELECT sub_id, mode, pos, idx FROM (SELECT sub_id, mode, idx, row_number() OVER (PARTITION BY sub_id, mode ORDER BY -ln(greatest({U('9', 'sub_id', 'mode', 'idx')}, 1e-300)) / weight, idx) AS pos FROM sw, range(4) s(sub_id)) WHERE pos <= {_LIMIT}")
def sample_weighted(spark: SparkSession, sf: str) -> DataFrame:
    return sampling.sample_by_hash(arrays.slice_weights(w.stored_log(spark, sf)), 4, SIDES, 9, weighted=True)


GRID = ENC + f", gr AS MATERIALIZED (SELECT mode, idx, ((row_number() OVER (PARTITION BY mode ORDER BY md5('9:' || mode || ':' || idx), idx) - 1) // ({_LIMIT}))::BIGINT AS segment FROM sw)"


@query("sample_grid", GRID + " SELECT * FROM gr")
def sample_grid(spark: SparkSession, sf: str) -> DataFrame:
    return sampling.grid_segments(arrays.slice_weights(w.stored_log(spark, sf)), SIDES, 9)


@query("grid_cube_nnz", GRID + " SELECT a.segment AS s1, b.segment AS s2, c.segment AS s3, count(*) AS nnz FROM e JOIN gr a ON a.mode = 1 AND a.idx = i1 JOIN gr b ON b.mode = 2 AND b.idx = i2 JOIN gr c ON c.mode = 3 AND c.idx = i3 GROUP BY ALL")
def grid_cube_nnz(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return sampling.grid_cubes(arr, sampling.grid_segments(arrays.slice_weights(arr), SIDES, 9)).groupBy("s1", "s2", "s3").agg(F.count("*").alias("nnz"))


@query("extract_blocks", PLAN + PLACES + " SELECT * FROM x")
def extract_blocks(spark: SparkSession, sf: str) -> DataFrame:
    arr, plan = _plan(spark, sf)
    return sampling.extract(arr, plan, SIDES)


@query("coverage", PLAN + PLACES + " SELECT s.sub_id, count(x.lin) AS nnz FROM range(4) s(sub_id) LEFT JOIN x USING (sub_id) GROUP BY ALL")
def coverage(spark: SparkSession, sf: str) -> DataFrame:
    arr, plan = _plan(spark, sf)
    return sampling.coverage(arr, plan, SIDES)


@query("budget_table", f'SELECT name AS "array", size, ceil(cells / (size::DOUBLE * size * size))::BIGINT AS count FROM ({_SIZES}), (VALUES (30), (80), (120), (180)) t(size)')
def budget_table(spark: SparkSession, sf: str) -> DataFrame:
    """Subarrays to coverage one, by their side, of the two large arrays."""
    sides = (30, 80, 120, 180)
    counts = F.explode(F.array(*[F.struct(F.lit(s).alias("size"), sampling.subarrays_for_coverage([s] * 3, F.col("cells")).cast("long").alias("count")) for s in sides]))
    return _sizes(spark, sf).select(F.col("name").alias("array"), counts.alias("x")).select("array", "x.*")


SHARDS = PLAN + ", sh AS (SELECT sub_id, ((row_number() OVER (ORDER BY md5('0:' || sub_id), sub_id) - 1) % 3)::INT AS shard FROM (SELECT DISTINCT sub_id FROM pl))"


@query("assign_shards", SHARDS + " SELECT * FROM sh")
def assign_shards(spark: SparkSession, sf: str) -> DataFrame:
    return sampling.assign_shards(_plan(spark, sf)[1], 3)


@query("shard_partition_counts", SHARDS + " SELECT shard, count(*) AS subs FROM sh GROUP BY shard")
def shard_partition_counts(spark: SparkSession, sf: str) -> DataFrame:
    return assign_shards(spark, sf).groupBy("shard").agg(F.count("*").alias("subs"))


@query("sample_block_local")
def sample_block_local(spark: SparkSession, sf: str) -> DataFrame:
    """Two stages: nonzeros go once to their super-block, subarrays are drawn inside each."""
    arr = w.stored_log(spark, sf)
    cubes = sampling.grid_cubes(arr, sampling.grid_segments(arrays.slice_weights(arr), [25, 5, 25], 9))
    key = F.concat_ws("-", "s1", "s2", "s3")
    mode = F.explode(F.array(*[F.struct(F.lit(k).alias("mode"), F.col(f"i{k}").alias("idx")) for k in (1, 2, 3)]))
    slices = cubes.select(key.alias("block"), mode.alias("x")).groupBy("block", "x.mode", "x.idx").agg(F.count("*").alias("weight"))
    from pyspark.sql import Window

    draw = -F.log(F.greatest(uniform(keyed(9, F.col("block"), F.col("mode"), F.col("idx"))), F.lit(1e-300))) / F.col("weight")
    return slices.withColumn("pos", F.row_number().over(Window.partitionBy("block", "mode").orderBy(draw, "idx"))).filter(F.col("pos") <= F.element_at(F.lit(SIDES), F.col("mode"))).select("block", "mode", "pos", "idx")


# ---- merging and bags

_DEL = "g AS MATERIALIZED (SELECT event_id % 4 AS shard, user_id, event_type, (props->>'$.k')::BIGINT AS k, CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END AS bought FROM events WHERE (props->>'$.k') IS NOT NULL AND user_id IS NOT NULL AND event_type IS NOT NULL), gd AS (SELECT shard, 1 AS mode, idx, k, bought FROM g JOIN d1 ON user_id::VARCHAR = d1.key UNION ALL SELECT shard, 2, idx, k, bought FROM g JOIN d2 ON event_type = d2.key), dv AS MATERIALIZED (SELECT shard, mode, idx, sum(k)::BIGINT AS k, sum(bought)::BIGINT AS bought, count(*) AS n FROM gd GROUP BY ALL), dl AS (SELECT shard, mode, idx, 0 AS d, (k::DOUBLE / n - 50) / 100 AS v FROM dv UNION ALL SELECT shard, mode, idx, 1, bought::DOUBLE / n - 0.5 FROM dv)"
_FAC = f"f AS (SELECT mode, idx, d, {U('11', 'mode', 'idx', 'd')} AS v FROM (SELECT 1 AS mode, idx FROM d1 UNION ALL SELECT 2, idx FROM d2), range(2) t(d))"


def _factors_and_deltas(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """Hash-seeded rows of the log's users and event types, and what four shards of its events would move them by."""
    modes = ("user_id", "event_type")
    rows = w.log_records(spark, sf).dropna(subset=list(w.LOG))
    dictionary = arrays.mode_dictionary(w.log_array(spark, sf), modes)
    factors = dictionary.select("mode", "idx", F.array(*[uniform(keyed(11, F.col("mode"), F.col("idx"), d)) for d in range(2)]).alias("vec"))
    at = F.explode(F.array(*[F.struct(F.lit(k).alias("mode"), F.col(m).cast("string").alias("key")) for k, m in enumerate(modes, 1)]))
    long = rows.select(F.pmod("event_id", F.lit(4)).cast("int").alias("shard"), at.alias("x"), F.col("k").cast("long").alias("k"), F.when(F.col("event_type") == "purchase", 1).otherwise(0).alias("bought"))
    sums = long.groupBy("shard", "x.mode", "x.key").agg(F.sum("k").alias("k"), F.sum("bought").alias("bought"), F.count("*").alias("n"))
    delta = F.array((F.col("k") / F.col("n") - 50) / 100, F.col("bought") / F.col("n") - 0.5)
    return factors, sums.join(dictionary.select("mode", "key", "idx"), ["mode", "key"]).select("shard", "mode", "idx", delta.alias("delta"))


def _flat(factors: DataFrame) -> DataFrame:
    return num(factors.select("mode", "idx", F.posexplode("vec").alias("d", "value")), "value")


for _merge, _n, _wrap in (("mean", "4", "{0}"), ("touched", "count(DISTINCT shard)", "{0}"), ("laplace", "4", "sign({0}) * greatest(abs({0}) - 0.2, 0)")):
    _value = _wrap.format("(f.v + coalesce(c.v, 0))")

    @query(f"merge_{_merge}", ENC + f", {_FAC}, {_DEL}, c AS (SELECT mode, idx, d, sum(v) / {_n} AS v FROM dl GROUP BY mode, idx, d) SELECT f.mode::INT AS mode, f.idx, f.d::INT AS d, round({_value}, 6) + 0.0 AS value FROM f LEFT JOIN c USING (mode, idx, d)")
    def merge_query(spark: SparkSession, sf: str, how: str = _merge) -> DataFrame:
        factors, deltas = _factors_and_deltas(spark, sf)
        return _flat(train.merge_factors(factors, deltas, 4, how, 0.2))


@query("decay_closed_form", "SELECT user_id, gap, round(start * pow(1 - 0.1::DOUBLE / (1.0 * 20), gap), 6) + 0.0 AS dev FROM (SELECT user_id, date_diff('day', max(ts)::DATE, (SELECT max(ts)::DATE FROM events)) AS gap, max(value) / 100 AS start FROM events WHERE user_id IS NOT NULL GROUP BY user_id)")
def decay_closed_form(spark: SparkSession, sf: str) -> DataFrame:
    """The prior's pull on a user's row in the days since the last event, a step a day, against its closed form in the SQL."""
    from collections.abc import Iterator

    import pandas as pd

    from .functions.gp import ShardState

    rows = table(spark, sf, "events").select("user_id", F.to_date("ts").alias("day"), "value")
    last = rows.dropna(subset=["user_id"]).groupBy("user_id").agg(F.max("day").alias("day"), (F.max("value") / 100).alias("start"))
    gaps = last.join(F.broadcast(rows.agg(F.max("day").alias("end"))), F.lit(True)).select("user_id", F.datediff("end", "day").cast("long").alias("gap"), "start")

    def pulled(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for user, gap, start in frame.itertuples(index=False):
                state = ShardState(lambda mode, idx: np.zeros(1), 20, 0.1, 1.0)
                state.deviation[0, user], state.seen[0, user], state.now = np.array([start]), 0, gap
                out.append((user, gap, float(state.settled((0, user))[0])))
            yield pd.DataFrame(out, columns=["user_id", "gap", "dev"])

    return num(gaps.mapInPandas(pulled, "user_id long, gap long, dev double"), "dev")


_BAGS = ENC + f", s AS (SELECT i1, i2, i3, bag, {U(chr(39) + 's' + chr(39), 'bag', 'i1', 'i2', 'i3')} AS mean, 1 + bag AS wt FROM e, range(10) b(bag))"


def _bag_scores(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf).join(F.broadcast(spark.range(10).toDF("bag")), F.lit(True))
    return arr.select("i1", "i2", "i3", uniform(keyed("s", F.col("bag"), F.col("i1"), F.col("i2"), F.col("i3"))).alias("mean"), (F.col("bag") + 1).alias("wt"))


@query("bag_mean", _BAGS + " SELECT i1, i2, i3, round(avg(mean), 6) AS mean, count(*) AS votes FROM s GROUP BY ALL")
def bag_mean(spark: SparkSession, sf: str) -> DataFrame:
    return num(predict.bag_mean(_bag_scores(spark, sf), ["i1", "i2", "i3"]), "mean")


@query("bag_weighted", _BAGS + " SELECT i1, i2, i3, round(sum(mean * wt) / sum(wt), 6) AS mean, count(*) AS votes FROM s GROUP BY ALL")
def bag_weighted(spark: SparkSession, sf: str) -> DataFrame:
    return num(predict.bag_mean(_bag_scores(spark, sf), ["i1", "i2", "i3"], "wt"), "mean")


@query("top_links", _BAGS + ", a AS (SELECT i1, i2, i3, round(avg(mean), 6) AS mean FROM s GROUP BY ALL) SELECT * FROM (SELECT i1, row_number() OVER (PARTITION BY i1 ORDER BY mean DESC, i2, i3)::INT AS rank, i2, i3, mean FROM a) WHERE rank <= 3")
def top_links(spark: SparkSession, sf: str) -> DataFrame:
    return predict.top_links(bag_mean(spark, sf), "i1", 3, ["i2", "i3"]).select("i1", "rank", "i2", "i3", "mean")


# ---- baselines' products


def _khatri_sql(k: int) -> str:
    others = [j for j in (1, 2, 3) if j != k]
    parts = [f"SELECT i{k} AS i, {d} AS r, round(sum(y * {_fu(others[0], d)} * {_fu(others[1], d)}), 4) + 0.0 AS v FROM e GROUP BY i{k}" for d in range(3)]
    return ENC + " " + " UNION ALL ".join(parts)


def _long(rows: DataFrame) -> DataFrame:
    return num(rows.select("i", F.posexplode("vec").alias("r", "v")), "v", digits=4)


for _k in (1, 2, 3):

    @query(f"mttkrp_mode{_k}", _khatri_sql(_k))
    def khatri(spark: SparkSession, sf: str, k: int = _k) -> DataFrame:
        arr = w.stored_log(spark, sf)
        return _long(baselines.mttkrp(arr, baselines.random_factors(spark, w.sizes_of(arr), 3, 11), k, 3))


@query("sparse_mttkrp", _khatri_sql(1))
def sparse_mttkrp(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return _long(baselines.sparse_mttkrp(arr, baselines.random_factors(spark, w.sizes_of(arr), 3, 11), 1, 3))


@query("gram_mode1", ENC + " SELECT l.i1 AS a, r.i1 AS b, sum(l.y * r.y) AS g FROM e l JOIN e r USING (i2, i3) GROUP BY ALL")
def gram_mode1(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.gram(w.stored_log(spark, sf), 1)


_DEG = " SELECT e.i1, e.i2, e.i3, a.weight::DOUBLE * b.weight * c.weight AS score FROM e JOIN sw a ON a.mode = 1 AND a.idx = i1 JOIN sw b ON b.mode = 2 AND b.idx = i2 JOIN sw c ON c.mode = 3 AND c.idx = i3"


@query("degree_score", ENC + _DEG)
def degree_score(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return baselines.degree_score(arr, arrays.slice_weights(arr)).drop("y")


@query("impute_mean", ENC + " SELECT round(sum(y) / (any_value(m1) * any_value(m2) * any_value(m3)), 9) AS value, (any_value(m1) * any_value(m2) * any_value(m3) - count(*))::BIGINT AS absent FROM e, m")
def impute_mean(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    a, b, c = w.sizes_of(arr)
    return num(baselines.impute(arr, a * b * c), "value", digits=9)


# ---- costs, protocol and measures


@query("cost_model", f"SELECT name, size, (m1 * m1 * m1 + m1 * cells) + (m2 * m2 * m2 + m2 * cells) + (m3 * m3 * m3 + m3 * cells) AS time_units_global, n / 16.0::DOUBLE * (3 * pow(size, 3) + 3 * size * pow(size, 3)) AS time_units_local, cells + (m1 * m1 + m2 * m2 + m3 * m3) AS space_global, pow(size, 3) + 3 * size * size AS space_local FROM (SELECT *, ceil(cells / pow(size, 3)) AS n FROM ({_SIZES}), (VALUES (50), (80), (120)) s(size))")
def cost_model(spark: SparkSession, sf: str) -> DataFrame:
    """Time and space of the global and the local model for the two large arrays, on 16 nodes."""
    m = [F.col(f"m{k}") for k in (1, 2, 3)]
    per = []
    for s in (50, 80, 120):
        n = sampling.subarrays_for_coverage([s] * 3, F.col("cells"))
        values = {"time_units_global": cost.time_units(m), "time_units_local": cost.local_time([s] * 3, n, 16), "space_global": cost.space_units(m), "space_local": F.lit(cost.space_units([s] * 3))}
        per.append(F.struct(F.lit(s).alias("size"), *[v.alias(name) for name, v in values.items()]))
    return _sizes(spark, sf).select("name", F.explode(F.array(*per)).alias("x")).select("name", "x.*")


_TU = U("2", "w1", "w2", "w3")


@query("kfold_counts", f"WITH {TR} SELECT floor({_TU} * 5)::BIGINT AS fold, count(*) AS n FROM r GROUP BY ALL")
def kfold_counts(spark: SparkSession, sf: str) -> DataFrame:
    return protocol.kfold(w.triple_counts(spark, sf), 5, 2, ["w1", "w2", "w3"]).groupBy("fold").agg(F.count("*").alias("n"))


@query("split_80_20", f"WITH {TR} SELECT CASE WHEN {_TU} < 0.8 THEN 'train' ELSE 'test' END AS part, count(*) AS n FROM r GROUP BY ALL")
def split_80_20(spark: SparkSession, sf: str) -> DataFrame:
    a, b = protocol.split(w.triple_counts(spark, sf), 0.8, 2, ["w1", "w2", "w3"])
    return a.agg(F.lit("train").alias("part"), F.count("*").alias("n")).unionByName(b.agg(F.lit("test").alias("part"), F.count("*").alias("n")))


def _zeros_sql(count: int, sets: int) -> str:
    at = ", ".join(f"floor({U('4', chr(39) + 'z' + chr(39), 'set_id', 'n', str(k))} * m{k})::BIGINT + 1 AS i{k}" for k in (1, 2, 3))
    return f", z AS MATERIALIZED (SELECT DISTINCT set_id, {at} FROM range({count}) c(n), range({sets}) s(set_id), m), zc AS MATERIALIZED (SELECT set_id, i1, i2, i3, 0.0::DOUBLE AS y FROM z WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.i1 = z.i1 AND e.i2 = z.i2 AND e.i3 = z.i3))"


@query("zero_candidates", ENC + _zeros_sql(500, 2) + " SELECT * FROM zc")
def zero_candidates(spark: SparkSession, sf: str) -> DataFrame:
    arr = w.stored_log(spark, sf)
    return protocol.zero_candidates(arr, w.sizes_of(arr), 500, 4, 2)


_SETS = ENC + _zeros_sql(400, 5) + f", rest AS (SELECT i1, i2, i3 FROM e WHERE {U('4', 'i1', 'i2', 'i3')} >= 0.8), ts AS MATERIALIZED (SELECT set_id, i1, i2, i3, 1.0::DOUBLE AS y FROM (SELECT set_id, i1, i2, i3, row_number() OVER (PARTITION BY set_id ORDER BY {U('4', chr(39) + 'o' + chr(39), 'set_id', 'i1', 'i2', 'i3')}, i1, i2, i3) AS n FROM rest, range(5) s(set_id)) WHERE n <= 50 UNION ALL SELECT set_id, i1, i2, i3, y FROM (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY {U('4', chr(39) + 'b' + chr(39), 'set_id', 'i1', 'i2', 'i3')}, i1, i2, i3) AS n FROM zc) WHERE n <= 200)"


def _test_sets(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    arr = w.stored_log(spark, sf)
    return arr, protocol.holdout_sets(arr, w.sizes_of(arr), 0.8, 5, 50, 200, 4)[1]


@query("test_sets", _SETS + " SELECT * FROM ts")
def test_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _test_sets(spark, sf)[1]


_SCORED = _SETS + ", sc AS MATERIALIZED (SELECT ts.set_id, ts.y, coalesce(a.weight, 0)::DOUBLE * coalesce(b.weight, 0) * coalesce(c.weight, 0) AS score FROM ts LEFT JOIN sw a ON a.mode = 1 AND a.idx = i1 LEFT JOIN sw b ON b.mode = 2 AND b.idx = i2 LEFT JOIN sw c ON c.mode = 3 AND c.idx = i3)"


def _scored(spark: SparkSession, sf: str) -> DataFrame:
    arr, sets = _test_sets(spark, sf)
    return baselines.degree_score(sets, arrays.slice_weights(arr)).select("set_id", "y", "score")


_AUC = "SELECT {by} sum(o * (below + z / 2.0)) / (sum(o) * sum(z)) AS auc FROM (SELECT *, coalesce(sum(z) OVER ({part} ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM (SELECT {by} {s} AS s, sum(CASE WHEN y > 0 THEN 1 ELSE 0 END)::DOUBLE AS o, sum(CASE WHEN y > 0 THEN 0 ELSE 1 END)::DOUBLE AS z FROM sc GROUP BY ALL)) {group}"
_BIN = "floor(least(greatest(score / (SELECT max(score) + 1 FROM sc) * 10000, 0), 9999))"


@query("auc_exact", _SCORED + " SELECT set_id, round(auc, 6) AS auc FROM (" + _AUC.format(by="set_id,", part="PARTITION BY set_id", s="score", group="GROUP BY set_id") + ")")
def auc_exact(spark: SparkSession, sf: str) -> DataFrame:
    return num(measures.auc(_scored(spark, sf), ["set_id"]), "auc")


@query("auc_pooled", _SCORED + " SELECT round(auc, 6) AS auc FROM (" + _AUC.format(by="", part="", s="score", group="") + ")")
def auc_pooled(spark: SparkSession, sf: str) -> DataFrame:
    return num(measures.auc(_scored(spark, sf)), "auc")


@query("auc_binned", _SCORED + " SELECT set_id, round(auc, 6) AS auc FROM (" + _AUC.format(by="set_id,", part="PARTITION BY set_id", s=_BIN, group="GROUP BY set_id") + ")")
def auc_binned(spark: SparkSession, sf: str) -> DataFrame:
    scored = _scored(spark, sf)
    high = scored.agg(F.max("score")).first()[0] + 1
    return num(measures.auc_binned(scored, ["set_id"], high=high), "auc")


@query("auc_summary", _SCORED + " SELECT round(avg(auc), 6) AS mean_auc, round(stddev_samp(auc), 6) AS sd_auc, count(auc) AS runs FROM (" + _AUC.format(by="set_id,", part="PARTITION BY set_id", s="score", group="GROUP BY set_id") + ")")
def auc_summary(spark: SparkSession, sf: str) -> DataFrame:
    return num(measures.summarize(measures.auc(_scored(spark, sf), ["set_id"])), "mean_auc", "sd_auc")


_P = "(score / (SELECT max(score) FROM sc))"


def _probable(spark: SparkSession, sf: str) -> DataFrame:
    scored = _scored(spark, sf)
    return scored.withColumn("prob", F.col("score") / scored.agg(F.max("score")).first()[0])


@query("rmse", _SCORED + f" SELECT round(sqrt(avg(pow(y - {_P}, 2))), 6) AS rmse, round(sqrt(avg(pow(y - {_P}, 2))) / sqrt(avg(pow(y - 0.2, 2))), 6) AS ratio FROM sc")
def rmse(spark: SparkSession, sf: str) -> DataFrame:
    return num(measures.rmse(_probable(spark, sf).withColumn("base", F.lit(0.2)), "prob", "base"), "rmse", "ratio")


@query("log_loss", _SCORED + f" SELECT round(-avg(CASE WHEN y > 0 THEN ln(least(greatest({_P}, 1e-9), 1 - 1e-9)) ELSE ln(1 - least(greatest({_P}, 1e-9), 1 - 1e-9)) END), 6) AS log_loss FROM sc")
def log_loss(spark: SparkSession, sf: str) -> DataFrame:
    return num(measures.log_loss(_probable(spark, sf)), "log_loss")


@query("scaling_curve", "WITH s AS MATERIALIZED (SELECT machines, max(n)::DOUBLE AS seconds FROM (SELECT machines, l_suppkey % machines AS at, count(*) AS n FROM lineitem, (VALUES (4), (8), (12), (16)) t(machines) WHERE l_suppkey IS NOT NULL GROUP BY ALL) GROUP BY machines) SELECT machines, seconds, round(seconds / b, 6) AS relative, round(b / seconds, 6) AS speedup FROM s, (SELECT seconds AS b FROM s WHERE machines = 4)")
def scaling_curve(spark: SparkSession, sf: str) -> DataFrame:
    """Order lines dealt to machines by their supplier, one a second on each: the busiest machine's time."""
    lines = table(spark, sf, "lineitem").dropna(subset=["l_suppkey"]).groupBy("l_suppkey").agg(F.count("*").alias("n"))
    dealt = lines.select("l_suppkey", "n", F.explode(F.array(*[F.lit(m) for m in (4, 8, 12, 16)])).alias("machines"))
    loads = dealt.groupBy("machines", F.pmod("l_suppkey", F.col("machines")).alias("at")).agg(F.sum("n").alias("n"))
    return num(measures.scaling_curve(loads.groupBy("machines").agg(F.max("n").cast("double").alias("seconds")), 4), "relative", "speedup")


@query("traffic_model", f"SELECT name, 8.0::DOUBLE * (m1 * r + m2 * r + m3 * r) AS factors, (m1 + m2 + m3) * (8.0::DOUBLE * r + 12) AS deltas, round(12.0::DOUBLE * 1.07::DOUBLE * nnz, 3) AS blocks FROM ({_SIZES}) JOIN (VALUES ('log', 10), ('orders', 5)) t(name, r) USING (name)")
def traffic_model(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of a round for the two large arrays: parent factors, changed rows (all, at this coverage), and once the blocks."""
    m = [F.col(f"m{k}") for k in (1, 2, 3)]
    out = None
    for name, r in (("log", 10), ("orders", 5)):
        parts = cost.traffic(m, [r] * 3, F.col("nnz"), 1.07, m[0] + m[1] + m[2])
        own = _sizes(spark, sf).filter(F.col("name") == name).select("name", *[v.alias(k) for k, v in parts.items()])
        out = own if out is None else out.unionByName(own)
    return num(out, "blocks", digits=3)
