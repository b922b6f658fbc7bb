"""Kernels on tensors of the tables, each against SQL; test matrices are integers, so sums are exact."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.counter import P, SECOND, gauss_col, mix_sql
from ..operators import algebra as A
from ..operators import index as X
from ..operators import metrics
from ..operators.constraints import nonneg, soft
from ..operators.cp import CPModel, updated
from ..operators.orth import gram_rows
from ..plans import cost
from ..sources import tables
from .base import FIVE, FOUR, NBM, PSC, UTE, built, query


def _simple(name: str, source: str, with_sql: str, order: int) -> None:
    columns = ", ".join(f"i{k + 1}" for k in range(order))
    query(name, f"WITH {with_sql} SELECT {columns}, v FROM t")(lambda spark, d: built(spark, d, source)[0].df)


for _name, _source, _sql, _order in (("tensor_build_nbm", "business", NBM, 3), ("tensor_build_orders5", "five_way", FIVE, 5), ("tensor_build_orders4", "orders_four", FOUR, 4), ("tensor_build_psc", "purchases", PSC, 3), ("tensor_build_events", "activity", UTE, 3)):
    _simple(_name, _source, _sql, _order)


_FOLD = "regexp_replace(translate(lower(coalesce(text, '')), 'abcdefghijklmnopqrstuvwxyz', 'ABCDEFGHIJKLMNOPQRSTUVWXYZ'), '[^A-Z]', '[', 'g')"


def _bigram_sql(source: str, key: str) -> str:
    return f"WITH x AS (SELECT {key} AS id, {_FOLD} AS t FROM {source}), p AS (SELECT id, t, unnest(range(1, length(t))) AS i FROM x) SELECT id, CAST(ascii(substr(t, i, 1)) - 65 AS BIGINT) AS a, CAST(ascii(substr(t, i + 1, 1)) - 65 AS BIGINT) AS b, count(*) AS n FROM p GROUP BY ALL"


@query("tensor_build_bigram", _bigram_sql("documents", "doc_id"))
def tensor_build_bigram(spark: SparkSession, d: str) -> DataFrame:
    return tables.bigrams(tables.table(spark, d, "documents"), "doc_id")


@query("op_benchmark_bigram", _bigram_sql("benchmark", "item_id"))
def benchmark_bigram(spark: SparkSession, d: str) -> DataFrame:
    return tables.bigrams(tables.table(spark, d, "benchmark"), "item_id")


@query("tensor_build_embeddings", "SELECT vec_id AS i1, CAST((p - 1) // 8 AS BIGINT) AS i2, CAST((p - 1) % 8 AS BIGINT) AS i3, CAST(embedding[p] AS DOUBLE) AS v FROM embeddings, range(1, 65) r(p)")
def tensor_build_embeddings(spark: SparkSession, d: str) -> DataFrame:
    return tables.embedding_cells(spark, d).df


@query("mode_dictionary", f"WITH {NBM} SELECT DISTINCT dense_rank() OVER (ORDER BY brand) - 1 AS idx, brand AS key FROM keyed")
def mode_dictionary(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "business")[1]["brand"]


@query("mode_dictionary_large", f"WITH {PSC} SELECT DISTINCT dense_rank() OVER (ORDER BY customer) - 1 AS idx, customer AS key FROM keyed")
def mode_dictionary_large(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "purchases")[1]["customer"]


@query("tensor_meta", f"WITH {NBM} SELECT max(i1) + 1 AS size1, max(i2) + 1 AS size2, max(i3) + 1 AS size3, count(*) AS cells, sum(v * v) AS norm2, round(count(*) / ((max(i1) + 1.0) * (max(i2) + 1) * (max(i3) + 1)), 6) AS density FROM t")
def tensor_meta(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return spark.createDataFrame([(*t.shape, t.df.count(), A.norm2(t.df), round(metrics.density(t), 6))], "size1 long, size2 long, size3 long, cells long, norm2 double, density double")


_SIZES = "z AS (SELECT max(i1) + 1 AS a, max(i2) + 1 AS b, max(i3) + 1 AS c FROM t)"
for _n, _col in ((0, "i2 + i3 * b"), (1, "i1 + i3 * a"), (2, "i1 + i2 * a")):
    query(f"unfold_mode{_n + 1}", f"WITH {NBM}, {_SIZES} SELECT i{_n + 1} AS row, {_col} AS col, v FROM t, z")(lambda spark, d, n=_n: X.unfold(built(spark, d, "business")[0].df, built(spark, d, "business")[0].shape, n))


@query("fold_roundtrip", f"WITH {NBM} SELECT i1, i2, i3, v FROM t")
def fold_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return X.fold(X.unfold(t.df, t.shape, 1), t.shape, 1)


@query("permute_modes", f"WITH {NBM} SELECT i3 AS i1, i1 AS i2, i2 AS i3, v FROM t")
def permute_modes(spark: SparkSession, d: str) -> DataFrame:
    return X.permute(built(spark, d, "business")[0].df, (2, 0, 1))


@query("ind2sub_grid", "SELECT c_custkey, id + 1 AS worker, id % 2 + 1 AS s1, (id // 2) % 4 + 1 AS s2, (id // 8) % 3 + 1 AS s3, (id // 2) % 4 + 1 AS unfold_row, id % 2 + 2 * ((id // 8) % 3) + 1 AS unfold_col FROM (SELECT c_custkey, CAST(c_custkey % 24 AS BIGINT) AS id FROM customer)")
def ind2sub_grid(spark: SparkSession, d: str) -> DataFrame:
    """Customers dealt over a 2 x 4 x 3 grid of workers."""
    return X.workers_of(tables.table(spark, d, "customer").select("c_custkey", (F.col("c_custkey") % 24).cast("long").alias("id")), (2, 4, 3), 1)


_BLOCKS = f"WITH {NBM}, {_SIZES}, p AS (SELECT i1, i2, i3, v, least(i1 * 2 // a, 1) AS s1, least(i2 * 3 // b, 2) AS s2, 0 AS s3 FROM t, z)"


def _block_cells(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    part = lambda k, g: F.least(F.floor(F.col(f"i{k + 1}") * g / t.shape[k]), F.lit(g - 1)).cast("long")
    return t.df.withColumn("s1", part(0, 2)).withColumn("s2", part(1, 3)).withColumn("s3", F.lit(0).cast("long"))


@query("block_assign", f"{_BLOCKS} SELECT i1, i2, i3, s1 + 2 * s2 + 6 * s3 AS block FROM p")
def block_assign(spark: SparkSession, d: str) -> DataFrame:
    s = [F.col(f"s{k}") for k in (1, 2, 3)]
    return _block_cells(spark, d).select("i1", "i2", "i3", X.sub2ind(s, (2, 3, 1)).alias("block"))


@query("block_stats", f"{_BLOCKS} SELECT s1, s2, CAST(s3 AS BIGINT) AS s3, count(*) AS cells, sum(v) AS total, sum(v * v) AS norm2 FROM p GROUP BY ALL")
def block_stats(spark: SparkSession, d: str) -> DataFrame:
    return _block_cells(spark, d).groupBy("s1", "s2", "s3").agg(F.count("*").alias("cells"), F.sum("v").alias("total"), F.sum(F.col("v") * F.col("v")).alias("norm2"))


@query("mode_marginals", f"WITH {NBM} SELECT i1, i2, i3, sum(v) AS v FROM t GROUP BY CUBE (i1, i2, i3)")
def mode_marginals(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "business")[0].df.cube("i1", "i2", "i3").agg(F.sum("v").alias("v"))


@query("slice_norms", f"WITH {NBM} SELECT i3, sum(v * v) AS norm2, count(*) AS cells FROM t GROUP BY i3")
def slice_norms(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "business")[0].df.groupBy("i3").agg(F.sum(F.col("v") * F.col("v")).alias("norm2"), F.count("*").alias("cells"))


@query("fiber_norms_topk", f"WITH {NBM} SELECT i1, i2, sum(v * v) AS norm2 FROM t GROUP BY ALL ORDER BY norm2 DESC, i1, i2 LIMIT 20")
def fiber_norms_topk(spark: SparkSession, d: str) -> DataFrame:
    return built(spark, d, "business")[0].df.groupBy("i1", "i2").agg(F.sum(F.col("v") * F.col("v")).alias("norm2")).orderBy(F.desc("norm2"), "i1", "i2").limit(20)


_U = "CAST((({i}) * 7 + {r} * 3) % 5 - 2 AS DOUBLE)"


def _u(i: str, r: object) -> str:
    return _U.format(i=i, r=r)


def _rows(spark: SparkSession, size: int, rank: int) -> DataFrame:
    return A.formula_rows(spark, size, rank)


@query("ttm_mode2", f"WITH {NBM} SELECT i1, r AS i2, i3, sum(v * {_u('i2', 'r')}) AS v FROM t, range(3) q(r) GROUP BY ALL")
def ttm_mode2(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return A.ttm(t.df, _rows(spark, t.shape[1], 3), 1, 3)


@query("ttm_chain_skip1", f"WITH {NBM} SELECT i1, r AS i2, s AS i3, sum(v * {_u('i2', 'r')} * {_u('i3', 's')}) AS v FROM t, range(3) q(r), range(2) w(s) GROUP BY ALL")
def ttm_chain_skip1(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return A.ttm_chain(t.df, [(_rows(spark, s, r), r) for s, r in zip(t.shape, (4, 3, 2), strict=True)], skip=0, sizes=t.shape)


@query("tucker_core_project", f"WITH {NBM} SELECT q AS i1, r AS i2, s AS i3, sum(v * {_u('i1', 'q')} * {_u('i2', 'r')} * {_u('i3', 's')}) AS v FROM t, range(2) a(q), range(3) b(r), range(2) c(s) GROUP BY ALL")
def tucker_core_project(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    mats = [np.array([[(i * 7 + r * 3) % 5 - 2 for r in range(k)] for i in range(s)], float) for s, k in zip(t.shape, (2, 3, 2), strict=True)]
    core = mats[2].T @ t.project(2, mats)
    return spark.createDataFrame([(q, r, s, float(core[s, q + 2 * r])) for q in range(2) for r in range(3) for s in range(2)], "i1 long, i2 long, i3 long, v double")


for _n, (_a, _b) in enumerate((("i2", "i3"), ("i1", "i3"), ("i1", "i2"))):
    query(f"mttkrp_mode{_n + 1}", f"WITH {NBM} SELECT i{_n + 1} AS i, CAST(r AS INTEGER) AS r, sum(v * {_u(_a, 'r')} * {_u(_b, 'r')}) AS v FROM t, range(3) q(r) GROUP BY ALL")(lambda spark, d, n=_n: A.mttkrp(built(spark, d, "business")[0].df, [_rows(spark, s, 3) for s in built(spark, d, "business")[0].shape], n, 3))


@query("mttkrp_columnwise", f"WITH {PSC} SELECT i2 AS i, CAST(r AS INTEGER) AS r, sum(v * {_u('i1', 'r')} * {_u('i3', 'r')}) AS v FROM t, range(3) q(r) GROUP BY ALL")
def mttkrp_columnwise(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "purchases")[0]
    return A.mttkrp(t.df, [_rows(spark, s, 3) for s in t.shape], 1, 3, "columnwise")


@query("mttkrp_blocks", f"WITH {NBM} SELECT i1 AS i, CAST(r AS INTEGER) AS r, sum(v * {_u('i2', 'r')} * {_u('i3', 'r')}) AS v FROM t, range(3) q(r) GROUP BY ALL")
def mttkrp_blocks(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    fs = [np.array([[(i * 7 + r * 3) % 5 - 2 for r in range(3)] for i in range(s)], float) for s in t.shape]
    return _matrix(spark, t.to_blocks((2, 2, 1)).mttkrp(fs, 0))


def _matrix(spark: SparkSession, m: np.ndarray, i: str = "i", r: str = "r", places: int | None = None) -> DataFrame:
    rows = [(a, b, float(x if places is None else round(x, places) + 0.0)) for a, row in enumerate(m) for b, x in enumerate(row)]
    return spark.createDataFrame(rows, f"{i} long, {r} int, v double")


#: Rows (i, numbers) of integers in tables: sums of their products are exact.
_MATRICES = {
    "order": ("orders", "o_orderkey", ["o_orderkey % 7 - 3", "o_custkey % 5 - 2", "year(o_orderdate) - 1995", "month(o_orderdate) - 6"]),
    "client": ("orders", "o_custkey", ["o_orderkey % 7 - 3", "year(o_orderdate) - 1995", "month(o_orderdate) - 6"]),
    "customer": ("customer", "c_custkey", ["c_nationkey - 12", "c_custkey % 5 - 2", "c_nationkey % 4"]),
    "part": ("part", "p_partkey", ["p_size - 25", "p_partkey % 5 - 2", "p_size % 4"]),
}


def _own(spark: SparkSession, d: str, name: str, rank: int) -> DataFrame:
    source, key, numbers = _MATRICES[name]
    return tables.table(spark, d, source).select(F.col(key).alias("i"), F.array(*[F.expr(x).cast("double") for x in numbers[:rank]]).alias("f"))


def _own_sql(name: str, rank: int) -> str:
    source, key, numbers = _MATRICES[name]
    return f"(SELECT {key} AS i, [{', '.join(f'CAST({x} AS DOUBLE)' for x in numbers[:rank])}] AS f FROM {source})"


def _gram_sql(name: str, rank: int) -> str:
    return f"SELECT r AS i, CAST(s AS INTEGER) AS r, sum(f[r + 1] * f[s + 1]) AS v FROM {_own_sql(name, rank)} a, range({rank}) b(r), range({rank}) c(s) GROUP BY r, s"


@query("gram", _gram_sql("order", 3))
def gram(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, A.gram(_own(spark, d, "order", 3), 3))


@query("gram_rows", _gram_sql("order", 4))
def gram_of_rows(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, gram_rows(_own(spark, d, "order", 4)))


@query("cross_gram", f"SELECT r AS i, CAST(s AS INTEGER) AS r, sum(a.f[r + 1] * g.f[s + 1]) AS v FROM {_own_sql('client', 3)} a JOIN {_own_sql('customer', 2)} g USING (i), range(3) b(r), range(2) c(s) GROUP BY r, s")
def cross_gram(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, A.gram(_own(spark, d, "client", 3), 3, _own(spark, d, "customer", 2), 2))


@query("gram_hadamard", f"SELECT x.i, x.r, x.v * y.v AS v FROM ({_gram_sql('client', 3)}) x JOIN ({_gram_sql('part', 3)}) y ON x.i = y.i AND x.r = y.r")
def gram_hadamard(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, A.gram_hadamard([A.gram(_own(spark, d, name, 3), 3) for name in ("client", "part", "customer")], 2))


#: Small matrices of whole tables: for each nation (year) the number of rows and two sums of integers.
_FOLDED = {"orders": "year(o_orderdate)", "customer": "c_nationkey"}
_SUMMED = {"orders": ("o_orderkey % 7 - 3", "month(o_orderdate)"), "customer": ("c_custkey % 5 - 2", "c_custkey % 7")}


def _folded(spark: SparkSession, d: str, name: str) -> np.ndarray:
    rows = tables.table(spark, d, name).groupBy(F.expr(_FOLDED[name]).alias("k")).agg(F.count("*"), *[F.sum(F.expr(x)) for x in _SUMMED[name]])
    return np.array([r[1:] for r in rows.orderBy("k").collect()], float).reshape(-1, 3)


def _folded_sql(name: str) -> str:
    sums = ", ".join(f"CAST({x} AS DOUBLE)" for x in ("count(*)", *[f"sum({x})" for x in _SUMMED[name]]))
    return f"(SELECT row_number() OVER (ORDER BY k) - 1 AS i, f FROM (SELECT {_FOLDED[name]} AS k, [{sums}] AS f FROM {name} GROUP BY k))"


_TWO = f"{_folded_sql('orders')} a, {_folded_sql('customer')} b, (SELECT count(DISTINCT {_FOLDED['orders']}) AS n FROM orders) z"


@query("khatri_rao", f"SELECT a.i + z.n * b.i AS i, CAST(r AS INTEGER) AS r, a.f[r + 1] * b.f[r + 1] AS v FROM {_TWO}, range(3) c(r)")
def khatri_rao(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, A.khatri_rao([_folded(spark, d, name) for name in _FOLDED]))


@query("kronecker", f"SELECT a.i + z.n * b.i AS i, CAST(r + 3 * s AS INTEGER) AS r, a.f[r + 1] * b.f[s + 1] AS v FROM {_TWO}, range(3) c(r), range(3) e(s)")
def kronecker(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, A.kronecker([_folded(spark, d, name) for name in _FOLDED]))


@query("outer", "SELECT a.n_nationkey AS i1, b.r_regionkey AS i2, CAST(a.n_regionkey * (b.r_regionkey + 1) AS DOUBLE) AS v FROM (SELECT CAST(n_nationkey AS BIGINT) AS n_nationkey, n_regionkey FROM nation) a, (SELECT CAST(r_regionkey AS BIGINT) AS r_regionkey FROM region) b")
def outer(spark: SparkSession, d: str) -> DataFrame:
    a = tables.table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("i"), F.col("n_regionkey").cast("double").alias("v"))
    b = tables.table(spark, d, "region").select(F.col("r_regionkey").cast("long").alias("i"), (F.col("r_regionkey") + 1).cast("double").alias("v"))
    return A.outer([a, b])


_SIGN = f"(1 - 2 * ({mix_sql(77, ['i2', 'i3', 'r'])} % 2))"


@query("sketch_rademacher_mode1", f"WITH {NBM} SELECT i1 AS i, CAST(r AS INTEGER) AS r, sum(v * {_SIGN}) AS v FROM t, range(4) q(r) GROUP BY ALL")
def sketch_rademacher_mode1(spark: SparkSession, d: str) -> DataFrame:
    return A.sketch(built(spark, d, "business")[0].df, 0, 4, 77, "signs")


@query("sketch_block_sum", f"WITH {NBM} SELECT i1 AS i, CAST(r AS INTEGER) AS r, sum(v * {_SIGN}) AS v FROM t, range(4) q(r) GROUP BY ALL")
def sketch_block_sum(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, built(spark, d, "business")[0].to_blocks((2, 4, 3)).sketch(0, 4, 77, "signs"))


@query("sketch_gram", f"WITH {NBM}, s AS (SELECT i1, r, sum(v * {_SIGN}) AS v FROM t, range(4) q(r) GROUP BY ALL) SELECT a.r AS i, CAST(b.r AS INTEGER) AS r, sum(a.v * b.v) AS v FROM s a JOIN s b USING (i1) GROUP BY a.r, b.r")
def sketch_gram(spark: SparkSession, d: str) -> DataFrame:
    z = built(spark, d, "business")[0].sketch(0, 4, 77, "signs")
    return _matrix(spark, z.T @ z)


_DRAWN = [f"({mix_sql(seed, ['o_orderkey', 'o_custkey'])} + 0.5) / {P}" for seed in (5, 5 + SECOND)]


@query("gaussian_moments", f"SELECT round(avg(x), 6) AS mean, round(stddev_pop(x), 6) AS sd, round(avg(pow((x - m) / s, 4)), 6) AS kurtosis FROM (SELECT x, avg(x) OVER () AS m, stddev_pop(x) OVER () AS s FROM (SELECT sqrt(-2 * ln({_DRAWN[0]})) * cos(2 * pi() * {_DRAWN[1]}) AS x FROM orders))")
def gaussian_moments(spark: SparkSession, d: str) -> DataFrame:
    """Moments of one number for each order, drawn by its keys."""
    x = tables.table(spark, d, "orders").select(gauss_col(5, [F.col("o_orderkey"), F.col("o_custkey")]).alias("x"))
    m = x.agg(F.avg("x").alias("m"), F.stddev_pop("x").alias("s"), F.kurtosis("x").alias("k"))
    return m.select(F.round("m", 6).alias("mean"), F.round("s", 6).alias("sd"), F.round(F.col("k") + 3, 6).alias("kurtosis"))


# One update from fixed positive factors w(i, r) = (7 i + 3 r) mod 5 + 1 -----------------------------------------


def _w(size: int, rank: int = 2) -> np.ndarray:
    return np.array([[(7 * i + 3 * r) % 5 + 1 for r in range(rank)] for i in range(size)], float)


def _step(spark: SparkSession, d: str, update: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    fs = [_w(s) for s in t.shape]
    q = t.mttkrp(fs, 0)
    return _matrix(spark, updated(fs[0], q, A.gram_hadamard([f.T @ f for f in fs], 0), update, nonneg() if update != "als" else soft(0)), places=5)


def _ws(i: str, r: object) -> str:
    return f"CAST((({i}) * 7 + {r} * 3) % 5 + 1 AS DOUBLE)"


_UPDATE = f"""WITH {NBM}, {_SIZES},
g AS (SELECT r, s, (SELECT sum({_ws('j', 'r')} * {_ws('j', 's')}) FROM range((SELECT b FROM z)) x(j)) * (SELECT sum({_ws('k', 'r')} * {_ws('k', 's')}) FROM range((SELECT c FROM z)) y(k)) AS v FROM range(2) a(r), range(2) e(s)),
m AS (SELECT (SELECT v FROM g WHERE r = 0 AND s = 0) AS t00, (SELECT v FROM g WHERE r = 0 AND s = 1) AS t01, (SELECT v FROM g WHERE r = 1 AND s = 1) AS t11),
q AS (SELECT i1 AS i, sum(v * {_ws('i2', 0)} * {_ws('i3', 0)}) AS q0, sum(v * {_ws('i2', 1)} * {_ws('i3', 1)}) AS q1, {_ws('i1', 0)} AS a0, {_ws('i1', 1)} AS a1 FROM t GROUP BY i1)"""


def _two(e0: str, e1: str, source: str = "q, m") -> str:
    return f"SELECT i, 0 AS r, round({e0}, 5) AS v FROM {source} UNION ALL SELECT i, 1 AS r, round({e1}, 5) AS v FROM {source}"


query("als_step_r2", f"{_UPDATE} " + _two("(q0 * t11 - q1 * t01) / (t00 * t11 - t01 * t01)", "(q1 * t00 - q0 * t01) / (t00 * t11 - t01 * t01)"))(lambda spark, d: _step(spark, d, "als"))
query("mu_step", f"{_UPDATE} " + _two("a0 * greatest(q0, 0) / (a0 * t00 + a1 * t01 + 1e-12)", "a1 * greatest(q1, 0) / (a0 * t01 + a1 * t11 + 1e-12)"))(lambda spark, d: _step(spark, d, "mu"))
query("hals_step_r2", f"{_UPDATE}, h AS (SELECT *, greatest(0, a0 + (q0 - a0 * t00 - a1 * t01) / t00) AS b0 FROM q, m) " + _two("b0", "greatest(0, a1 + (q1 - b0 * t01 - a1 * t11) / t11)", "h"))(lambda spark, d: _step(spark, d, "hals"))


@query("soft_threshold", "SELECT CAST(i AS BIGINT) AS i, CAST(0 AS INTEGER) AS r, CAST(sign(i - 10) * greatest(abs(i - 10) - 3, 0) AS DOUBLE) AS v FROM range(21) x(i)")
def soft_threshold(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, soft(3)(np.arange(-10.0, 11.0)[:, None]))


@query("nonneg_project", "SELECT CAST(i AS BIGINT) AS i, CAST(0 AS INTEGER) AS r, CAST(greatest(i - 10 - 3, 0) AS DOUBLE) AS v FROM range(21) x(i)")
def nonneg_project(spark: SparkSession, d: str) -> DataFrame:
    return _matrix(spark, (nonneg() & soft(3))(np.arange(-10.0, 11.0)[:, None]))


# Measures from fixed models -------------------------------------------------------------------------------------


@query("fit_cp_fixed", f"WITH {NBM}, {_SIZES}, g AS (SELECT i1, i2, i3 FROM range((SELECT a FROM z)) x(i1), range((SELECT b FROM z)) y(i2), range((SELECT c FROM z)) w(i3)), all_cells AS (SELECT i1, i2, i3, coalesce(v, 0) AS v FROM g LEFT JOIN t USING (i1, i2, i3)) SELECT round(1 - sqrt(sum(pow(v - {_ws('i1', 0)} * {_ws('i2', 0)} * {_ws('i3', 0)} - {_ws('i1', 1)} * {_ws('i2', 1)} * {_ws('i3', 1)}, 2)) / sum(v * v)), 6) AS fit FROM all_cells")
def fit_cp_fixed(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return spark.createDataFrame([(round(metrics.fit(t, CPModel([_w(s) for s in t.shape])), 6),)], "fit double")


@query("reconstruct_cells", f"WITH {NBM} SELECT i1, i2, i3, v, {_u('i1', 0)} * {_u('i2', 0)} * {_u('i3', 0)} + {_u('i1', 1)} * {_u('i2', 1)} * {_u('i3', 1)} AS w FROM t")
def reconstruct_cells(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0]
    return A.reconstruct(t.df, [_rows(spark, s, 2) for s in t.shape], 2)


@query("norm_inner_difference", f"WITH {NBM}, s AS (SELECT i1, i2, i3, v FROM t WHERE i3 % 2 = 0), o AS (SELECT i1, i2, i3, 2 * v AS v FROM t WHERE i3 % 3 = 0) SELECT (SELECT sum(v * v) FROM s) AS norm2, (SELECT sum(s.v * o.v) FROM s JOIN o USING (i1, i2, i3)) AS inner_product, (SELECT sum(pow(coalesce(s.v, 0) - coalesce(o.v, 0), 2)) FROM s FULL JOIN o USING (i1, i2, i3)) AS difference2")
def norm_inner_difference(spark: SparkSession, d: str) -> DataFrame:
    t = built(spark, d, "business")[0].df
    s, o = t.filter("i3 % 2 = 0"), t.filter("i3 % 3 = 0").withColumn("v", F.col("v") * 2)
    return spark.createDataFrame([(A.norm2(s), A.inner(s, o), A.norm2(A.subtract(s, o)))], "norm2 double, inner_product double, difference2 double")


@query("snr_db", "SELECT round(10 * log10(sum(value * value) / sum(pow(value - floor(value), 2))), 4) AS snr FROM events")
def snr_db(spark: SparkSession, d: str) -> DataFrame:
    e = tables.table(spark, d, "events").agg(F.sum(F.col("value") * F.col("value")).alias("a"), F.sum(F.pow(F.col("value") - F.floor("value"), F.lit(2))).alias("b")).first()
    return spark.createDataFrame([(round(metrics.snr_db(e["a"], e["b"]), 4),)], "snr double")


@query("sir_fixed", "WITH e AS (SELECT vec_id AS i, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS a FROM embeddings), x AS (SELECT i, k, a[k] AS t, a[k] + 0.01 * (i % 7) AS f FROM e, range(1, 65) r(k)), m AS (SELECT k, avg(t) AS mt, stddev_pop(t) AS st, avg(f) AS mf, stddev_pop(f) AS sf FROM x GROUP BY k) SELECT CAST(k - 1 AS INTEGER) AS r, round(10 * log10(sum(pow((t - mt) / st, 2)) / sum(pow((t - mt) / st - (f - mf) / sf, 2))), 4) AS sir_db FROM x JOIN m USING (k) GROUP BY k")
def sir_fixed(spark: SparkSession, d: str) -> DataFrame:
    rows = tables.table(spark, d, "embeddings").orderBy("vec_id").select("vec_id", "embedding").collect()
    a, i = np.array([r["embedding"] for r in rows], float), np.array([r["vec_id"] for r in rows])
    s = metrics.sir(a, -2 * (a + 0.01 * (i % 7)[:, None])[:, ::-1])
    return spark.createDataFrame([(r, round(float(x), 4)) for r, x in enumerate(s)], "r int, sir_db double")


@query("cost_model", "SELECT y, CAST(i AS BIGINT) AS size, 10.0 * i * i * i AS direct, CAST(i * 400 + 20 * 8000 AS DOUBLE) AS compressed, 1.0 * i * i * i AS full_numbers, CAST(8000 + 3 * i * 20 AS DOUBLE) AS form_numbers FROM (SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(count(DISTINCT o_custkey) AS DOUBLE) AS i FROM orders GROUP BY y)")
def cost_model(spark: SparkSession, d: str) -> DataFrame:
    """Costs of cubes as long as the customers that ordered in a year are many."""
    years = tables.table(spark, d, "orders").groupBy(F.year("o_orderdate").alias("y")).agg(F.count_distinct("o_custkey").alias("i")).collect()
    rows = [(y, i, cost.gradient_flops((i,) * 3, 10), cost.gradient_flops((i,) * 3, 10, (20,) * 3), cost.full_numbers((i,) * 3), cost.form_numbers((i,) * 3, (20,) * 3)) for y, i in years]
    return spark.createDataFrame(rows, "y int, size long, direct double, compressed double, full_numbers double, form_numbers double")


@query("planner_choice", "SELECT * FROM (VALUES ('business', 'blocks', 'two_sweep'), ('purchases', 'cells', 'two_sweep')) v(source, layout, method)")
def planner_choice(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for name, sizes in (("business", (10, 10, 10)), ("purchases", (20, 20, 20))):
        t = built(spark, d, name)[0]
        p = cost.choose(t.df, t.shape, sizes)
        rows.append((name, p.layout, p.method))
    return spark.createDataFrame(rows, "source string, layout string, method string")

