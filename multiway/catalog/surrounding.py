"""Operators around the methods: sources, sinks, joins, aggregations, windows, sets, scalar functions, SQL surface."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import surface
from ..operators import tucker
from ..sources import io, tables
from ..sources.storage import new_path
from .base import FOUR, NBM, built, query

c = F.col


def T(spark: SparkSession, d: str, name: str) -> DataFrame:
    return tables.table(spark, d, name)


def _add(name: str, sql: str, f) -> None:
    query(f"op_{name}", sql)(f)


def _nbm(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "business")[0].df


# Scans, filters, projections
_add("scan_prune", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_discount > 0.05", lambda s, d: T(s, d, "lineitem").filter((c("l_quantity") >= 49) & (c("l_discount") > 0.05)).select("l_orderkey", "l_quantity"))
_add("project_expr", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem", lambda s, d: T(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(c("l_extendedprice") * (1 - c("l_discount")), 4).alias("net")))
_add("drop_zero", f"WITH {NBM} SELECT i1, i2, i3, v FROM t WHERE v > 40", lambda s, d: _nbm(s, d).withColumn("v", F.greatest(c("v") - 40, F.lit(0.0))).filter("v <> 0").withColumn("v", c("v") + 40))
_add("dedup", "SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem", lambda s, d: T(s, d, "lineitem").select("l_orderkey", "l_linenumber").dropDuplicates())
_add("filter_slice", f"WITH {NBM} SELECT i1, i2, i3, v FROM t WHERE i1 BETWEEN 2 AND 5 AND i3 < 10", lambda s, d: _nbm(s, d).filter(c("i1").between(2, 5) & (c("i3") < 10)))
_add("between", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20", lambda s, d: T(s, d, "part").filter(c("p_size").between(10, 20)).select("p_partkey"))
_add("isin", "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') OR o_orderstatus = 'P'", lambda s, d: T(s, d, "orders").filter(c("o_orderpriority").isin("1-URGENT", "2-HIGH") | (c("o_orderstatus") == "P")).select("o_orderkey"))
_add("like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%1%' AND p_type LIKE '%E%'", lambda s, d: T(s, d, "part").filter(c("p_name").like("%1%") & c("p_type").like("%E%")).select("p_partkey", "p_name"))
_add("case_bucket", "SELECT CASE WHEN o_totalprice < 50000 THEN 'low' WHEN o_totalprice < 200000 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM orders GROUP BY 1", lambda s, d: T(s, d, "orders").groupBy(F.when(c("o_totalprice") < 50000, "low").when(c("o_totalprice") < 200000, "mid").otherwise("high").alias("band")).agg(F.count("*").alias("n")))
_add("width_bucket", "SELECT CAST(least(floor(o_totalprice / 25000), 19) AS BIGINT) AS bin, count(*) AS n FROM orders GROUP BY 1", lambda s, d: T(s, d, "orders").groupBy((F.expr("width_bucket(o_totalprice, 0D, 500000D, 20)") - 1).alias("b")).agg(F.count("*").alias("m")).groupBy(F.least("b", F.lit(19)).cast("long").alias("bin")).agg(F.sum("m").alias("n")))

# Joins
_J = "SELECT s_nationkey, sum(l_quantity) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1"
for _name, _hint in (("broadcast", "broadcast"), ("sortmerge", "merge"), ("shufflehash", "shuffle_hash")):
    _add(f"join_{_name}", _J, lambda s, d, h=_hint: T(s, d, "lineitem").join(T(s, d, "supplier").hint(h), c("l_suppkey") == c("s_suppkey")).groupBy("s_nationkey").agg(F.sum("l_quantity").alias("q")))
_add("join_nested_loop", "SELECT a.n_nationkey, b.r_regionkey FROM nation a JOIN region b ON a.n_regionkey < b.r_regionkey", lambda s, d: T(s, d, "nation").join(T(s, d, "region"), c("n_regionkey") < c("r_regionkey")).select("n_nationkey", "r_regionkey"))
_add("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1", lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), c("c_custkey") == c("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
_add("join_full", f"WITH {NBM}, a AS (SELECT * FROM t WHERE i3 = 0), b AS (SELECT * FROM t WHERE i3 = 1) SELECT coalesce(a.i1, b.i1) AS i1, coalesce(a.i2, b.i2) AS i2, coalesce(a.v, 0) - coalesce(b.v, 0) AS v FROM a FULL JOIN b ON a.i1 = b.i1 AND a.i2 = b.i2", lambda s, d: _nbm(s, d).filter("i3 = 0").select("i1", "i2", "v").join(_nbm(s, d).filter("i3 = 1").select("i1", "i2", c("v").alias("w")), ["i1", "i2"], "full").select("i1", "i2", (F.coalesce("v", F.lit(0.0)) - F.coalesce("w", F.lit(0.0))).alias("v")))
_add("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", lambda s, d: T(s, d, "customer").join(T(s, d, "orders").filter("o_totalprice > 300000"), c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"))
_add("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), c("c_custkey") == c("o_custkey"), "left_anti").select("c_custkey"))
_add("join_cross", "SELECT n_nationkey, r_regionkey, s FROM nation, region, range(3) x(s)", lambda s, d: T(s, d, "nation").crossJoin(T(s, d, "region")).crossJoin(s.range(3).withColumnRenamed("id", "s")).select("n_nationkey", "r_regionkey", "s"))
_add("join_self_gram", f"WITH {FOUR} SELECT a.i2 AS i, b.i2 AS j, sum(a.v * b.v) AS v FROM t a JOIN t b USING (i1, i3, i4) GROUP BY a.i2, b.i2", lambda s, d: (lambda g: s.createDataFrame([(i, j, float(x)) for i, r in enumerate(g) for j, x in enumerate(r)], "i long, j long, v double"))(built(s, d, "orders_four")[0].gram(1)))
_add("join_range", "WITH b AS (SELECT CAST(k AS INTEGER) AS k, k * 25.0 AS lo, (k + 1) * 25.0 AS hi FROM range(4) x(k)) SELECT k, count(*) AS n FROM events JOIN b ON value >= lo AND value < hi GROUP BY k", lambda s, d: T(s, d, "events").join(F.broadcast(s.createDataFrame([(k, 25.0 * k, 25.0 * k + 25) for k in range(4)], "k int, lo double, hi double")), (c("value") >= c("lo")) & (c("value") < c("hi"))).groupBy("k").agg(F.count("*").alias("n")))
_ASOF = "SELECT e.event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.event_id < e.event_id) AS last_purchase FROM events e WHERE e.event_type = 'click'"
_add("join_asof", _ASOF, lambda s, d: T(s, d, "events").select("event_id", "user_id", "event_type", F.max(F.when(c("event_type") == "purchase", c("event_id"))).over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)).alias("last_purchase")).filter("event_type = 'click'").select("event_id", "last_purchase"))
_add("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 6 HOUR", lambda s, d: T(s, d, "events").filter("event_type = 'click'").select(c("event_id").alias("a"), c("user_id").alias("u"), c("ts").alias("t")).join(T(s, d, "events").filter("event_type = 'purchase'"), (c("u") == c("user_id")) & (c("ts") >= c("t")) & (c("ts") < c("t") + F.expr("INTERVAL 6 HOURS"))).select("a", c("event_id").alias("b")))
_add("join_salted", _J, lambda s, d: surface.salted_join(T(s, d, "lineitem"), T(s, d, "supplier"), "l_suppkey", "s_suppkey", 8).groupBy("s_nationkey").agg(F.sum("l_quantity").alias("q")))

# Aggregations
_add("agg_hash", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, count(*) AS n, avg(l_quantity) AS a FROM lineitem GROUP BY 1, 2", lambda s, d: T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"), F.avg("l_quantity").alias("a")))
_add("agg_distinct", "SELECT s_nationkey, count(DISTINCT l_partkey) AS parts FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1", lambda s, d: T(s, d, "lineitem").join(T(s, d, "supplier"), c("l_suppkey") == c("s_suppkey")).groupBy("s_nationkey").agg(F.countDistinct("l_partkey").alias("parts")))
_add("agg_stats", "SELECT event_type, count(*) AS n, round(avg(value), 4) AS mean, round(stddev_samp(value), 4) AS sd, min(value) AS low, max(value) AS high FROM events GROUP BY 1", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 4).alias("mean"), F.round(F.stddev_samp("value"), 4).alias("sd"), F.min("value").alias("low"), F.max("value").alias("high")))
_add("agg_filter", "SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS n, sum(l_quantity) FILTER (WHERE l_tax < 0.02) AS q FROM lineitem GROUP BY 1", lambda s, d: T(s, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.when(c("l_discount") > 0.05, 1)).alias("n"), F.sum(F.when(c("l_tax") < 0.02, c("l_quantity"))).alias("q")))
_add("agg_corr", "SELECT round(corr(l_quantity, l_extendedprice), 5) AS r, round(covar_pop(l_quantity, l_extendedprice), 2) AS cv FROM lineitem", lambda s, d: T(s, d, "lineitem").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 5).alias("r"), F.round(F.covar_pop("l_quantity", "l_extendedprice"), 2).alias("cv")))
_add("agg_maxby", "SELECT user_id, max_by(event_type, event_id) AS last_type, min_by(event_type, event_id) AS first_type FROM events GROUP BY 1", lambda s, d: T(s, d, "events").groupBy("user_id").agg(F.max_by("event_type", "event_id").alias("last_type"), F.min_by("event_type", "event_id").alias("first_type")))
_add("grouping_sets", f"WITH {FOUR} SELECT i1, i2, sum(v) AS v FROM t GROUP BY GROUPING SETS ((i1), (i2), (i1, i2), ())", lambda s, d: built(s, d, "orders_four")[0].df.groupingSets([["i1"], ["i2"], ["i1", "i2"], []], "i1", "i2").agg(F.sum("v").alias("v")))
_add("cube", f"WITH {FOUR} SELECT i3, i4, sum(v) AS v FROM t GROUP BY CUBE (i3, i4)", lambda s, d: built(s, d, "orders_four")[0].df.cube("i3", "i4").agg(F.sum("v").alias("v")))
_add("rollup", f"WITH {FOUR} SELECT i2, i3, sum(v) AS v FROM t GROUP BY ROLLUP (i2, i3)", lambda s, d: built(s, d, "orders_four")[0].df.rollup("i2", "i3").agg(F.sum("v").alias("v")))
_add("pivot_factor", f"WITH {FOUR} SELECT i2, sum(v) FILTER (WHERE i4 = 0) AS s0, sum(v) FILTER (WHERE i4 = 1) AS s1, sum(v) FILTER (WHERE i4 = 2) AS s2 FROM t GROUP BY i2", lambda s, d: built(s, d, "orders_four")[0].df.groupBy("i2").pivot("i4", [0, 1, 2]).agg(F.sum("v")).toDF("i2", "s0", "s1", "s2"))
_add("unpivot_factor", f"WITH {FOUR} SELECT i2, i4, sum(v) AS v FROM t GROUP BY i2, i4", lambda s, d: built(s, d, "orders_four")[0].df.groupBy("i2").pivot("i4", [0, 1, 2]).agg(F.sum("v")).toDF("i2", "0", "1", "2").unpivot("i2", ["0", "1", "2"], "i4", "v").select("i2", c("i4").cast("long").alias("i4"), "v").filter("v IS NOT NULL"))
_add("approx_distinct", "SELECT true AS within", lambda s, d: T(s, d, "lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.countDistinct("l_partkey") - 1) < 0.1).alias("within")))
_add("percentile_exact", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY 1", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median")))

# Windows, sorts, sets
_o = lambda: Window.partitionBy("o_custkey").orderBy("o_orderkey")  # noqa: E731  Columns need a session, so they are made late
for _name, _sql, _col in (
    ("win_rownumber", "row_number() OVER w", lambda: F.row_number().over(_o())), ("win_lag", "lag(o_totalprice) OVER w", lambda: F.lag("o_totalprice").over(_o())),
    ("win_ntile", "ntile(3) OVER w", lambda: F.ntile(3).over(_o())), ("win_firstlast", "first_value(o_orderkey) OVER w", lambda: F.first("o_orderkey").over(_o())),
    ("win_running", "round(sum(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2)", lambda: F.round(F.sum("o_totalprice").over(_o().rowsBetween(-2, 0)), 2)),
):
    _cast = "INTEGER" if _name in ("win_rownumber", "win_ntile") else None
    _value = f"CAST({_sql} AS {_cast})" if _cast else _sql
    _add(_name, f"SELECT o_orderkey, {_value} AS x FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)", lambda s, d, x=_col: T(s, d, "orders").select("o_orderkey", x().alias("x")))
_b = lambda: Window.partitionBy("p_brand").orderBy("p_size")
for _name, _sql, _col in (("win_rank", "CAST(rank() OVER w AS INTEGER)", lambda: F.rank().over(_b())), ("win_denserank", "CAST(dense_rank() OVER w AS INTEGER)", lambda: F.dense_rank().over(_b())), ("win_percentrank", "round(percent_rank() OVER w, 6)", lambda: F.round(F.percent_rank().over(_b()), 6))):
    _add(_name, f"SELECT p_partkey, {_sql} AS x FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)", lambda s, d, x=_col: T(s, d, "part").select("p_partkey", x().alias("x")))
_add("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part", lambda s, d: T(s, d, "part").select("p_partkey", F.count("*").over(_b().rangeBetween(-2, 2)).alias("near")))
_add("sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", lambda s, d: T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice"))
_add("topk_per_group", f"WITH {NBM} SELECT i3, i1, i2, v FROM (SELECT *, row_number() OVER (PARTITION BY i3 ORDER BY v DESC, i1, i2) AS k FROM t) WHERE k <= 3", lambda s, d: _nbm(s, d).withColumn("k", F.row_number().over(Window.partitionBy("i3").orderBy(F.desc("v"), "i1", "i2"))).filter("k <= 3").select("i3", "i1", "i2", "v"))
_C = "SELECT c_nationkey AS k FROM customer"
_S = "SELECT s_nationkey AS k FROM supplier"
_cs = lambda s, d: (T(s, d, "customer").select(c("c_nationkey").alias("k")), T(s, d, "supplier").select(c("s_nationkey").alias("k")))
_add("union", f"{_C} UNION ALL {_S}", lambda s, d: (lambda x: x[0].union(x[1]))(_cs(s, d)))
_add("unionbyname", f"SELECT k, 1 AS src FROM ({_C}) UNION ALL SELECT k, 2 AS src FROM ({_S})", lambda s, d: (lambda x: x[0].withColumn("src", F.lit(1)).unionByName(x[1].select(F.lit(2).alias("src"), "k")))(_cs(s, d)))
_add("intersect", f"{_C} INTERSECT {_S}", lambda s, d: (lambda x: x[0].intersect(x[1]))(_cs(s, d)))
_add("except", f"{_C} EXCEPT {_S}", lambda s, d: (lambda x: x[0].subtract(x[1]))(_cs(s, d)))
_add("distinct", f"SELECT DISTINCT k FROM ({_C})", lambda s, d: _cs(s, d)[0].distinct())

# Scalar functions
_add("math", "SELECT event_id, round(sqrt(value), 6) AS a, round(ln(value + 1), 6) AS b, floor(value) % 7 AS m, CAST(sign(value - 50) AS DOUBLE) AS g FROM events", lambda s, d: T(s, d, "events").select("event_id", F.round(F.sqrt("value"), 6).alias("a"), F.round(F.ln(c("value") + 1), 6).alias("b"), (F.floor("value") % 7).cast("double").alias("m"), F.signum(c("value") - 50).alias("g")))
_add("string", "SELECT p_partkey, lower(p_name) AS a, length(p_name) AS n, substr(p_brand, 1, 5) AS b, md5(p_type) AS h FROM part", lambda s, d: T(s, d, "part").select("p_partkey", F.lower("p_name").alias("a"), F.length("p_name").alias("n"), F.substring("p_brand", 1, 5).alias("b"), F.md5(c("p_type").cast("binary")).alias("h")))
_add("date_modes", "SELECT event_id, hour(ts) AS h, dayofmonth(ts) AS d, month(ts) AS m FROM events", lambda s, d: T(s, d, "events").select("event_id", F.hour("ts").alias("h"), F.dayofmonth("ts").alias("d"), F.month("ts").alias("m")))
_add("json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", lambda s, d: T(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
_add("array_posexplode", "SELECT vec_id, CAST(p - 1 AS INTEGER) AS p, CAST(embedding[p] AS DOUBLE) AS x FROM embeddings, range(1, 65) r(p)", lambda s, d: T(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("p", "y")).select("vec_id", "p", c("y").cast("double").alias("x")))
_add("array_hof", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n FROM embeddings", lambda s, d: T(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n")))
_add("map", "SELECT event_type, count(*) AS n FROM events GROUP BY 1", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select(F.explode("m").alias("event_type", "n")))
_add("struct", "SELECT n_nationkey, n_name, n_regionkey FROM nation", lambda s, d: T(s, d, "nation").select(F.struct("n_nationkey", F.struct("n_name", "n_regionkey").alias("o")).alias("x")).select("x.n_nationkey", "x.o.n_name", "x.o.n_regionkey"))
_add("html_text", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages", lambda s, d: T(s, d, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("n")))
_add("null_semantics", "SELECT c_custkey, count(o_totalprice) AS n, sum(coalesce(o_totalprice, 0)) IS NOT NULL AS filled FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1", lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), c("c_custkey") == c("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_totalprice").alias("n"), F.sum(F.coalesce("o_totalprice", F.lit(0.0))).isNotNull().alias("filled")))
_add("docs_by_label", "SELECT quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL", lambda s, d: T(s, d, "documents").join(T(s, d, "labels"), "doc_id").groupBy("quality", "toxic").agg(F.count("*").alias("n")))
_add("conv_tensor", "SELECT conv_id, turn, role, CAST(sum(length(text)) AS DOUBLE) AS v FROM conversations GROUP BY ALL", lambda s, d: tables.keyed_cells(T(s, d, "conversations"), [("conv_id", c("conv_id")), ("turn", c("turn")), ("role", c("role"))], F.length("text")))

# Sources and sinks
_N = "SELECT n_nationkey, n_name, n_regionkey FROM nation"
for _kind in ("csv", "json", "orc"):
    _add(f"source_{_kind}", _N, lambda s, d, k=_kind: io.round_trip(T(s, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), k))
_add("source_text", "SELECT n_name AS value FROM nation", lambda s, d: io.round_trip(T(s, d, "nation").select(c("n_name").alias("value")), "text"))
_CELLS = f"WITH {NBM} SELECT i1, i2, i3, v FROM t"
_add("roundtrip_partitioned", _CELLS, lambda s, d: io.read_cells(s, io.write_cells(_nbm(s, d), new_path(s, "cells"), 4)))
_add("roundtrip_bucketed", f"WITH {NBM} SELECT i1, sum(v) AS v FROM t GROUP BY i1", lambda s, d: io.bucketed(_nbm(s, d), "i1", 4).groupBy("i1").agg(F.sum("v").alias("v")))
_add("source_blocks", _CELLS, lambda s, d: io.read_blocks(s, io.write_blocks(built(s, d, "business")[0].to_blocks((2, 2, 2)), new_path(s, "blocks")), built(s, d, "business")[0].shape).to_cells().df)
_add("source_synth", "SELECT a AS i1, b AS i2, c AS i3, CAST((a + 1) * (b + 2) * (c + 3) AS DOUBLE) AS v FROM range(4) x(a), range(5) y(b), range(6) z(c)", lambda s, d: io.synthetic(s, (4, 5, 6)))


@query("op_sink_model", "SELECT true AS same")
def sink_model(spark: SparkSession, d: str) -> DataFrame:
    form = tucker.sketch_tucker(built(spark, d, "business")[0], (3, 3, 3), 2)
    path = new_path(spark, "model")
    form.save(spark, path)
    return spark.createDataFrame([(bool(np.allclose(tucker.TuckerModel.load(spark, path).dense(), form.dense())),)], "same boolean")


# SQL surface
_add("udf_dot", "SELECT a.vec_id, round(list_sum(list_transform(a.embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS dot FROM embeddings a", lambda s, d: surface.register(s).sql(f"SELECT vec_id, round(mw_dot(embedding, embedding), 5) AS dot FROM parquet.`{d}/embeddings.parquet`"))
_add("udaf_gram", "SELECT CAST(0 AS INTEGER) AS i, round(sum(CAST(embedding[1] AS DOUBLE) * embedding[2]), 5) AS v FROM embeddings", lambda s, d: T(s, d, "embeddings").agg(surface.gram_entry(c("embedding")[0].cast("double"), c("embedding")[1].cast("double")).alias("g")).select(F.lit(0).alias("i"), F.round("g", 5).alias("v")))
_add("udtf_unfold", "SELECT vec_id, CAST((p - 1) // 8 AS BIGINT) AS i, CAST((p - 1) % 8 AS BIGINT) AS j, CAST(embedding[p] AS DOUBLE) AS v FROM embeddings, range(1, 65) r(p)", lambda s, d: surface.register(s).sql(f"SELECT vec_id, i, j, v FROM parquet.`{d}/embeddings.parquet`, LATERAL mw_cells(CAST(embedding AS array<double>), 8)"))
_add("sql_ind2sub", "SELECT id, id % 3 AS a, (id // 3) % 4 AS b FROM range(24) x(id)", lambda s, d: surface.register(s).sql("SELECT id, mw_ind2sub(id, 1, 3) AS a, mw_ind2sub(id, 3, 4) AS b FROM range(24)"))
_add("sql_fit", "SELECT event_type, round(1 - sqrt((sum(value * value) - sum(value) * sum(value) / count(*)) / sum(value * value)), 6) AS fit FROM events GROUP BY 1", lambda s, d: (tables.table(surface.register(s), d, "events").createOrReplaceTempView("mw_events"), s.sql("SELECT event_type, round(mw_fit(n2, c2), 6) AS fit FROM (SELECT event_type, sum(value * value) AS n2, sum(value) * sum(value) / count(*) AS c2 FROM mw_events GROUP BY 1)"))[1])
