"""Whole methods: recovery of planted integer tensors against SQL that makes the same cells, and checks of the experiments."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import workloads as W
from ..operators import baselines, cp, metrics, ntd, tucker
from ..operators.cluster import cluster_accuracy
from ..operators.constraints import nonneg, soft
from ..sources import synth, tables
from .base import NBM, built, query

SIZE, RANK = 24, 3

_NORMAL = f"e AS (SELECT vec_id AS i, list_transform(embedding[1:9], lambda x: CAST(floor(12 * CAST(x AS DOUBLE) + 0.5) AS BIGINT)) AS a FROM embeddings WHERE vec_id < {SIZE})"
_EXPONENTIAL = f"f AS (SELECT event_id // {SIZE * RANK} AS n, (event_id // {RANK}) % {SIZE} AS i, event_id % {RANK} AS r, CAST(floor(value / 40) AS BIGINT) AS x FROM events WHERE event_id < {3 * SIZE * RANK}), e AS (SELECT i, list(CASE WHEN (31 * i + 17 * r + 7 * (i // 11)) % 10 = 0 THEN 0 ELSE x END ORDER BY n, r) AS a FROM f GROUP BY i)"


def _cells_sql(planted: str) -> str:
    value = " + ".join(f"x.a[{r + 1}] * y.a[{r + 4}] * z.a[{r + 7}]" for r in range(RANK))
    return f"WITH {planted} SELECT x.i AS i1, y.i AS i2, z.i AS i3, {value} AS v FROM e x, e y, e z"


_kept: dict = {}


def _planted(spark: SparkSession, d: str, kind: str):
    key = (spark.sparkContext.applicationId, d, kind)
    if key not in _kept:
        fs = synth.normal_factors(spark, d, 3, SIZE, RANK, True) if kind == "normal" else synth.exponential_factors(spark, d, 3, SIZE, RANK, 10, True)
        t, truth = synth.cp_tensor(spark, fs, None, (2, 1, 1))
        t = t.kept()
        _kept[key] = (t, t.to_cells().kept(), truth)
    return _kept[key]


def _form(t):
    return tucker.sketch_tucker(t, [RANK] * 3, 5, "two_sweep")


EXACT = {"n_starts": 4, "tol": 1e-13, "max_iter": 3000}


def _recover(name: str, kind: str, method: Callable) -> None:
    sql = _cells_sql(_NORMAL if kind == "normal" else _EXPONENTIAL)

    def run(spark: SparkSession, d: str) -> DataFrame:
        t, cells, _ = _planted(spark, d, kind)
        return synth.model_cells(spark, method(t, cells))

    query(f"{name}_recover", sql)(run)


R3 = [RANK] * 3
for _name, _kind, _method in (
    ("hosvd", "normal", lambda t, c: tucker.hosvd(t, R3)),
    ("hosvd_sequential", "normal", lambda t, c: tucker.hosvd(c, R3, sequential=True)),
    ("tucker_als", "normal", lambda t, c: tucker.tucker_als(t, R3, 2)),
    ("tucker_als_random", "normal", lambda t, c: tucker.tucker_als(t, R3, 4, init="random")),
    ("sst", "normal", lambda t, c: tucker.sketch_tucker(c, R3, 5, "sequential")),
    ("sst_rademacher", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 5, "sequential", dist="signs")),
    ("sst_qr", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 5, "sequential", how="qr")),
    ("sst_power", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 0, "sequential", power=1)),
    ("tst", "normal", lambda t, c: tucker.sketch_tucker(c, R3, 5, "two_sweep")),
    ("tst_one_sweep", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 5, "two_sweep", sweeps=1)),
    ("tst_warm", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 5, "two_sweep", init="sequential")),
    ("dst_eager", "normal", lambda t, c: tucker.sketch_tucker(c.to_blocks((2, 4, 3)), R3, 5, "sequential", reduce="eager")),
    ("dst_lazy", "normal", lambda t, c: tucker.sketch_tucker(c.to_blocks((2, 4, 3)), R3, 5, "sequential", reduce="lazy")),
    ("dst_two_sweep", "normal", lambda t, c: tucker.sketch_tucker(c.to_blocks((1, 1, 4)), R3, 5, "two_sweep")),
    ("dst_broadcast", "normal", lambda t, c: tucker.sketch_tucker(t, R3, 5, "sequential", omega="broadcast")),
    ("fst", "normal", lambda t, c: tucker.fiber_sample_tucker(c, R3, 12)),
    ("fst_uniform", "normal", lambda t, c: tucker.fiber_sample_tucker(c, R3, 12, p="uniform")),
    ("est_unbiased", "normal", lambda t, c: tucker.entry_sample_tucker(c, R3, 1.0)),
    ("ccp_als", "normal", lambda t, c: cp.compressed_cp(_form(t), RANK, "als", **EXACT)),
    ("ccp_als_explicit", "normal", lambda t, c: cp.compressed_cp(_form(t), RANK, "als", how="explicit", **EXACT)),
    ("ccp_als_columnwise", "normal", lambda t, c: cp.compressed_cp(_form(t), RANK, "als", how="columnwise", **EXACT)),
    ("ccp_als_reuse", "normal", lambda t, c: cp.compressed_cp(_form(t), RANK, "als", how="reuse", **EXACT)),
    ("ccp_pg", "exponential", lambda t, c: cp.compressed_cp(_form(t), RANK, "pg", constraint=nonneg(), init="uniform", n_starts=2, tol=1e-15, max_iter=20_000)),
    ("ccp_hals", "exponential", lambda t, c: cp.compressed_cp(_form(t), RANK, "hals", **EXACT)),
    ("ccp_mu", "exponential", lambda t, c: cp.compressed_cp(_form(t), RANK, "mu", **EXACT)),
    ("ccp_als_nonneg", "exponential", lambda t, c: cp.compressed_cp(_form(t), RANK, "als", constraint=nonneg(), init="uniform", **EXACT)),
    ("ccp_per_mode", "exponential", lambda t, c: cp.compressed_cp(_form(t), RANK, "hals", constraint={0: nonneg(), 2: nonneg()}, **EXACT)),
    ("ctl", "normal", lambda t, c: cp.core_then_lift_cp(_form(t), RANK, tol=1e-13, max_iter=3000)),
    ("cdc", "exponential", lambda t, c: cp.core_domain_cp(_form(t), RANK, nonneg(), max_iter=3000, tol=1e-13)),
    ("cntd", "exponential", lambda t, c: ntd.compressed_ntd(_form(t), R3, max_iter=6000, tol=1e-14)),
    ("dcp_als", "normal", lambda t, c: cp.cp_als(t, RANK, init="svd", max_iter=60, tol=1e-12)),
    ("dcp_als_extrapolated", "normal", lambda t, c: cp.cp_als(t, RANK, init="svd", extrapolate=True, max_iter=60, tol=1e-12)),
    ("dcp_mu", "exponential", lambda t, c: max((cp.fit_cp(cp.DenseSource(t.dense()), RANK, "mu", init="uniform", seed=1 + 1000 * k, max_iter=3000, tol=1e-13) for k in range(4)), key=lambda m: m.history[-1])),
    ("ntd", "exponential", lambda t, c: ntd.ntd(t.dense(), R3, max_iter=6000, tol=1e-14)),
    ("dcp_hals", "exponential", lambda t, c: cp.cp_hals(t, RANK, max_iter=60, tol=1e-13)),
    ("rcp", "normal", lambda t, c: cp.cp_als(t, RANK, "reuse", init="svd", max_iter=60, tol=1e-12)),
    ("scm", "normal", lambda t, c: cp.cp_als(c, RANK, "columnwise", init="svd", max_iter=30, tol=1e-9)),
    ("amr", "normal", lambda t, c: baselines.anchored_replica_cp(t, RANK)),
    ("gpm", "normal", lambda t, c: baselines.partition_merge_cp(t, RANK)),
    ("ssm", "normal", lambda t, c: baselines.sampled_cp(t, RANK)),
):
    _recover(_name, _kind, _method)


def _checked(name: str, labels: list[str], run: Callable[[SparkSession, str], list[bool]]) -> None:
    """A query of (claim, passed) rows; every claim must hold."""
    values = ", ".join(f"('{x}', true)" for x in labels)

    def go(spark: SparkSession, d: str) -> DataFrame:
        return spark.createDataFrame([(x, bool(y)) for x, y in zip(labels, run(spark, d), strict=True)], "claim string, passed boolean")

    query(name, f"SELECT * FROM (VALUES {values}) v(claim, passed)")(go)


def _rows(frame: DataFrame) -> dict[tuple[str, str], dict]:
    return {(r["method"], r["config"]): r.asDict() for r in frame.collect()}


_measured: dict = {}


def _table(name: str, make: Callable[[SparkSession, str], DataFrame], claims: dict[str, Callable[[dict], bool]], shared: bool = True) -> None:
    """Register the metric rows of an experiment, and the claims that its rows must bear out, which run it once.

    shared=False: each of the two queries runs it anew, on the tables as it finds them.
    """

    def rows(spark: SparkSession, d: str) -> list:
        if not shared:
            return make(spark, d).collect()
        key = (spark.sparkContext.applicationId, d, name)
        if key not in _measured:
            _measured[key] = make(spark, d).collect()
        return _measured[key]

    query(name)(lambda spark, d: spark.createDataFrame(rows(spark, d), W.SCHEMA))

    def check(spark: SparkSession, d: str) -> list[bool]:
        mean: dict[str, dict] = {}
        for r in rows(spark, d):
            own = mean.setdefault(r["method"] if name not in BY_CONFIG else f"{r['method']} {r['config']}", {})
            for k in ("fit_obs", "fit_truth", "sir_db", "accuracy", "seconds", "passes"):
                if r[k] is not None:
                    own.setdefault(k, []).append(r[k])
        averaged = {m: {k: float(np.mean(v)) for k, v in values.items()} for m, values in mean.items()}
        return [claim(averaged) for claim in claims.values()]

    _checked(f"claims_{name}", list(claims), check)


BY_CONFIG = ("fit_table_w1", "fit_table_w2", "two_stage_w9")
_snr = lambda m, s: f"{m} 16^3 R=4 snr={s}"
_table("fit_table_w1", lambda spark, d: W.w1_snr_routes(spark, d, size=16, order=3, rank=4, snrs=(-10, 10, 20), seeds=(0, 1), max_iter=300), {
    "compression does not cost fit at 20 dB": lambda r: r[_snr("compressed_als", 20)]["fit_truth"] > r[_snr("direct_als", 20)]["fit_truth"] - 0.05,
    "fit rises with SNR": lambda r: r[_snr("compressed_als", -10)]["fit_truth"] < r[_snr("compressed_als", 10)]["fit_truth"],
    "core-then-lift is close when nothing is constrained": lambda r: abs(r[_snr("compressed_als", 20)]["fit_truth"] - r[_snr("core_then_lift", 20)]["fit_truth"]) < 0.1,
})
_w2 = lambda r, m, s, k="fit_truth": r[f"{m} 80^3 R=4 p=4 snr={s}"][k]
_table("fit_table_w2", lambda spark, d: W.w2_sketch_fit(spark, d, size=80, rank=4, p=4, snrs=(0, 20)), {
    "two sweeps are not worse than one pass": lambda r: all(_w2(r, "two_sweep", s) >= _w2(r, "sequential", s) - 1e-6 for s in (0, 20)),
    "two sweeps with a power step are close to the HOSVD of the same rank": lambda r: all(abs(_w2(r, "two_sweep_power", s) - _w2(r, "hosvd", s)) < 0.01 for s in (0, 20)),
    "one pass loses more under heavy noise": lambda r: _w2(r, "hosvd", 0) - _w2(r, "sequential", 0) >= _w2(r, "hosvd", 20) - _w2(r, "sequential", 20),
    "two sweeps read the data six times and its norm once": lambda r: _w2(r, "two_sweep", 20, "passes") == 7,
})
_table("fit_table_w3", lambda spark, d: W.w3_cp_table(spark, d, ((3, 60, 5),), seeds=(0, 1, 2)), {
    "compressed is not worse than direct": lambda r: r["compressed_als_best_of_5"]["fit_truth"] > r["direct_als"]["fit_truth"] - 0.01,
    "compressed iterations are faster than direct ones": lambda r: r["compressed_als"]["seconds"] < r["direct_als"]["seconds"],
    "compressed reads nothing": lambda r: r["compressed_als"]["passes"] == 0,
    "reuse reads less than direct": lambda r: r["reuse_als_2_sweeps_of_passes"]["passes"] < r["direct_als_2_sweeps_of_passes"]["passes"],
    "replicas suffer from noise": lambda r: r["anchored_replicas"]["fit_truth"] < r["compressed_als"]["fit_truth"],
})
_table("fit_table_w4", lambda spark, d: W.w4_nonneg_table(spark, d, ((3, 60, 5),), seeds=(0, 1, 2)), {
    "compressed updates recover": lambda r: min(r["compressed_hals"]["fit_truth"], r["compressed_mu"]["fit_truth"]) > 0.95,
    "compressed is not worse than direct, column-wise": lambda r: r["compressed_hals"]["fit_truth"] > r["direct_hals"]["fit_truth"] - 0.01,
    "compressed is not worse than direct, multiplicative": lambda r: r["compressed_mu"]["fit_truth"] > r["direct_mu"]["fit_truth"] - 0.01,
    "compressed column-wise is faster than direct": lambda r: r["compressed_hals"]["seconds"] < r["direct_hals"]["seconds"],
})
_table("huge_w7", lambda spark, d: W.w7_huge_nonneg(spark, d), {"components are recovered beyond 200 dB": lambda r: r["compressed_hals"]["sir_db"] > 200})
_table("huge_w7_generated", lambda spark, d: W.w7_huge_nonneg(spark, d, max_iter=1000, generated=True), {"components drawn by all orders are recovered beyond 200 dB": lambda r: r["compressed_hals"]["sir_db"] > 200}, shared=False)
_table("cluster_lang", lambda spark, d: W.w8_text_clustering(spark, d, plane=("two_sweep", "compressed_ntd_on_two_sweep")), {
    "document clusters follow language": lambda r: all(r[m]["accuracy"] > 0.5 for m in ("tucker_als", "two_sweep", "sequential")),
    "the two-sweep sketch fits as well as alternating": lambda r: r["two_sweep"]["fit_obs"] > r["tucker_als"]["fit_obs"] - 0.03,
    "the sequential sketch comes close": lambda r: r["sequential"]["fit_obs"] > r["tucker_als"]["fit_obs"] - 0.05,
    "nonnegativity costs fit": lambda r: r["compressed_ntd_on_two_sweep"]["fit_obs"] <= r["two_sweep"]["fit_obs"],
})
_checked("cluster_control", ["labels without signal stay near chance"], lambda spark, d: [W.w8_control(spark, d).first()["accuracy"] < 0.35])
_table("two_stage_w9", lambda spark, d: W.w9_two_stage(spark, d).unionByName(W.w9_two_stage(spark, d, "business")), {
    "fit rises with rank": lambda r: r["two_sweep five_way ranks 1"]["fit_obs"] < r["two_sweep five_way ranks 3"]["fit_obs"] < r["two_sweep five_way ranks 10"]["fit_obs"],
    "nonnegative CP fits no better than its form": lambda r: all(r[f"compressed_hals {f} R=10"]["fit_obs"] <= r[f"two_sweep {f} ranks 10"]["fit_obs"] + 1e-6 for f in ("five_way", "business")),
    "stage two reads nothing": lambda r: r["compressed_als five_way R=10"]["passes"] == 0,
})
_checked("replica_noise_w11", ["perfect without noise", "hurt by noise"], lambda spark, d: (lambda r: [r["anchored_replicas", "snr=None"]["fit_truth"] > 0.999, r["anchored_replicas", "snr=10.0"]["fit_truth"] < 0.9])(_rows(W.w11_replica_noise(spark, d, 30, 3))))


def _w12(spark, d):
    rows = W.w12_grids(spark, d, 24, 3).collect()
    by = {}
    for r in rows:
        by.setdefault(r["method"].replace("_lazy", "").replace("_eager", ""), []).append(r["fit_truth"])
    return [max(x) - min(x) < 1e-8 for x in (by["sequential"], by["two_sweep"])]


_checked("grids_w12", ["one-pass sketches agree over grids, eager and lazy", "two-sweep sketches agree over grids"], _w12)
_checked("random_numbers_w13", ["regenerated numbers send nothing", "quality is the same"], lambda spark, d: (lambda r: [r["counter_megabytes_sent", "I=40"]["accuracy"] == 0 < r["broadcast_megabytes_sent", "I=40"]["accuracy"], abs(r["counter", "I=40"]["fit_obs"] - r["broadcast", "I=40"]["fit_obs"]) < 0.05])(_rows(W.w13_random_numbers(spark, d, 40, 3))))
_checked("sampling_w14", ["sketches beat sampled entries under noise", "sketches beat sampled fibers under noise"], lambda spark, d: (lambda r: [r["two_sweep"] > r["entry_sampled"], r["two_sweep"] > r["fiber_sampled"]])({x["method"]: x["fit_truth"] for x in W.w14_sampling(spark, d).collect()}))


@query("scaling_w5")
def scaling_w5(spark: SparkSession, d: str) -> DataFrame:
    return W.w5_scaling_in_memory(spark, d)


@query("scaling_w6")
def scaling_w6(spark: SparkSession, d: str) -> DataFrame:
    return W.w6_scaling_compact(spark, d)


@query("sparse_w10")
def sparse_w10(spark: SparkSession, d: str) -> DataFrame:
    return W.w10_sparse(spark, d, 4)


def _sparse(spark, d):
    t, _, _ = _planted(spark, d, "exponential")
    form = _form(t)
    shares = [np.mean([(f == 0).mean() for f in cp.compressed_cp(form, RANK, "hals", constraint=nonneg() & soft(c, scaled=True), max_iter=100).factors]) for c in (0.0, 1e3, 1e6)]
    return [shares[0] <= shares[1] + 0.02, shares[1] <= shares[2] + 0.02, shares[2] > shares[0]]


_checked("sparsity_threshold", ["a small threshold does not fill zeros", "a larger one neither", "a large threshold makes zeros"], _sparse)


def _rows_method(spark, d):
    """Factor rows that stay on the executors give the same as the driver's loop."""
    t, _, _ = _planted(spark, d, "exponential")
    form = _form(t)
    start = cp.compressed_cp(form, RANK, "hals", max_iter=5, tol=0)
    modes = [spark.createDataFrame([(i, [float(x) for x in u[i]], [float(x) for x in a[i]]) for i in range(len(u))], "i long, u array<double>, a array<double>") for u, a in zip(form.factors, start.factors, strict=True)]
    _, history = cp.compressed_rows(modes, form.core, RANK, "hals", max_iter=3, tol=0)
    local = cp.compressed_cp(form, RANK, "hals", init=start.factors, max_iter=3, tol=0)
    return [abs(history[-1] - local.history[-1]) < 1e-6]


_checked("compressed_rows_agree", ["rows on executors give the same fit"], _rows_method)


def _bounds(spark, d):
    t, cells, truth = _planted(spark, d, "normal")
    low, high = tucker.tucker_error_bound(t, (2, 2, 2))
    form = tucker.hosvd(t, (2, 2, 2))
    error = form.norm2 - float((form.core**2).sum())
    return [low <= error * (1 + 1e-9), error <= high * (1 + 1e-9)]


_checked("tucker_error_bound", ["the error is at least the largest tail", "the error is at most the sum of tails"], _bounds)


@query("accuracy_perm4", """WITH c AS (SELECT dense_rank() OVER (ORDER BY lang) - 1 AS l, doc_id % 4 AS k FROM documents), n AS (SELECT l, k, count(*) AS n FROM c GROUP BY ALL),
p AS (SELECT a, b, x, y FROM range(4) q(a), range(4) w(b), range(4) e(x), range(4) r(y) WHERE a <> b AND a <> x AND a <> y AND b <> x AND b <> y AND x <> y)
SELECT round(max(s) / (SELECT count(*) FROM c), 6) AS accuracy FROM (SELECT a, b, x, y, sum(n) AS s FROM p, n WHERE (l = 0 AND k = a) OR (l = 1 AND k = b) OR (l = 2 AND k = x) OR (l = 3 AND k = y) GROUP BY ALL)""")
def accuracy_perm4(spark: SparkSession, d: str) -> DataFrame:
    pairs = tables.table(spark, d, "documents").select(F.col("lang").alias("label"), (F.col("doc_id") % 4).alias("cluster"))
    return spark.createDataFrame([(round(cluster_accuracy(pairs), 6),)], "accuracy double")


@query("fit_table_w3_200")
def fit_table_w3_200(spark: SparkSession, d: str) -> DataFrame:
    """The published size N=3, I=200, R=10 at 10 dB: compression and compressed ALS, timed apart."""
    return W.w3_cp_table(spark, d, ((3, 200, 10),), direct=False, replicas=False, sweeps=0)


@query("fit_table_w4_200")
def fit_table_w4_200(spark: SparkSession, d: str) -> DataFrame:
    """The same size with exponential factors and zeros: compressed nonnegative methods."""
    return W.w4_nonneg_table(spark, d, ((3, 200, 10),), direct=())


_table("baselines_w3_200", lambda spark, d: W.w3_cp_table(spark, d, ((3, 200, 10),), replicas=False, sweeps=0), {
    "compressed is not worse than direct": lambda r: r["compressed_als_best_of_5"]["fit_truth"] > r["svd_start_extrapolated_als"]["fit_truth"] - 0.01,
    "compressed iterations are faster": lambda r: r["compressed_als"]["seconds"] < r["direct_als"]["seconds"],
})
_table("baselines_w4_200", lambda spark, d: W.w4_nonneg_table(spark, d, ((3, 200, 10),)), {
    "compressed is not worse than direct": lambda r: all(r[f"compressed_{u}"]["fit_truth"] > r[f"direct_{u}"]["fit_truth"] - 0.01 for u in ("mu", "hals")),
    "compressed iterations are faster": lambda r: all(r[f"compressed_{u}"]["seconds"] < r[f"direct_{u}"]["seconds"] for u in ("mu", "hals")),
})


#: Six modes: with p=10 a core would have 15^6 numbers for 20^6 cells, so the oversampling is 3 there.
_table("fit_table_w3_six_way", lambda spark, d: W.w3_cp_table(spark, d, ((6, 20, 5),), direct=False, replicas=False, p=3, sweeps=0, generated=True), {
    "compressed recovers": lambda r: r["compressed_als_best_of_5"]["fit_truth"] > 0.98,
    "a power step helps the compression": lambda r: r["two_sweep_power_compression"]["fit_truth"] > r["two_sweep_compression"]["fit_truth"],
    "compressed reads nothing": lambda r: r["compressed_als"]["passes"] == 0,
})
_table("fit_table_w4_six_way", lambda spark, d: W.w4_nonneg_table(spark, d, ((6, 20, 5),), direct=(), p=3, generated=True), {
    "compressed multiplicative recovers": lambda r: r["compressed_mu"]["fit_truth"] > 0.98,
    "compressed reads nothing": lambda r: r["compressed_mu"]["passes"] == r["compressed_hals"]["passes"] == 0,
})

_table("fit_table_w4_500", lambda spark, d: W.w4_nonneg_table(spark, d, ((3, 500, 20),), direct=(), generated=True), {
    "compressed updates recover": lambda r: min(r["compressed_hals"]["fit_truth"], r["compressed_mu"]["fit_truth"]) > 0.98,
    "compressed reads nothing": lambda r: r["compressed_mu"]["passes"] == r["compressed_hals"]["passes"] == 0,
})


@query("fit_table_w3_500")
def fit_table_w3_500(spark: SparkSession, d: str) -> DataFrame:
    """The published size N=3, I=500, R=20 at 10 dB, factors drawn from counters: compression and compressed ALS, timed apart."""
    return W.w3_cp_table(spark, d, ((3, 500, 20),), direct=False, replicas=False, sweeps=0, generated=True)


@query("monte_carlo_w3")
def monte_carlo_w3(spark: SparkSession, d: str) -> DataFrame:
    """Mean, deviation and failures over the seeds of fit_table_w3."""
    from .base import QUERIES

    return W.monte_carlo_table(QUERIES["fit_table_w3"](spark, d))


@query("dst_rows_recover", _cells_sql(_NORMAL))
def dst_rows_recover(spark: SparkSession, d: str) -> DataFrame:
    """The sequential sketch whose bases stay rows on the executors."""
    _, cells, _ = _planted(spark, d, "normal")
    bases, core = tucker.sketch_tucker_rows(cells, R3, 5)
    factors = []
    for n, rows in enumerate(bases):
        u = np.zeros((SIZE, core.shape[n]))
        for r in rows.collect():
            u[r["i"]] = r["f"]
        factors.append(u)
    return synth.model_cells(spark, tucker.TuckerModel(core, factors))


@query("fit_tucker_fixed", f"WITH {NBM}, s AS (SELECT sum(v * v) AS n2, sum(v) AS total, count(DISTINCT i1) * count(DISTINCT i2) * count(DISTINCT i3) AS cells FROM t) SELECT round(1 - sqrt((n2 - total * total / cells) / n2), 6) AS fit FROM s")
def fit_tucker_fixed(spark: SparkSession, d: str) -> DataFrame:
    """Fit of the rank-one form with constant bases: its core is the sum of all cells over the root of their number."""
    t = built(spark, d, "business")[0]
    core = t.project(2, [np.full((s, 1), s**-0.5) for s in t.shape]).sum() * t.shape[2] ** -0.5
    return spark.createDataFrame([(round(metrics.fit_tucker(t.norm2(), np.array([core])), 6),)], "fit double")
