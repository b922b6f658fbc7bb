"""The experiment workloads on planted and table tensors. Each gives rows of one schema:
workload, method, config, seed, fit_obs, fit_truth, sir_db, accuracy, seconds, passes, iterations.

Methods that are compared have the same limit of iterations and the same tolerance. Direct methods on tensors that fit the
driver run there (the kindest setting for them, as in the published experiments); what a sweep costs as passes over distributed
data is shown beside."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from math import ceil

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, cluster, cp, metrics, ntd, tall, tucker
from .operators.orth import orth
from .operators.tensors import BLOCK, BlockTensor, plan_grid
from .plans import cost
from .session import setting
from .sources import synth, tables

SCHEMA = "workload string, method string, config string, seed int, fit_obs double, fit_truth double, sir_db double, accuracy double, seconds double, passes int, iterations int"


class Log:
    def __init__(self, workload: str):
        self.workload, self.rows = workload, []
        self.norms: dict[int, tuple] = {}  # of tensors, beside the tensor itself so that its id stays its own

    def run(self, method: str, config: str, seed: int, make: Callable, t=None, truth=None, reads: bool = True):
        """Time a method; its fit to the observed tensor and to the planted truth are taken outside the clock."""
        before = t.passes.reads if t is not None else 0
        began = time.perf_counter()
        model = make()
        seconds = time.perf_counter() - began
        passes = (t.passes.reads - before) if t is not None and reads else 0
        if t is not None and id(t) not in self.norms:
            self.norms[id(t)] = (t, t.norm2())
        obs = metrics.fit(t, model, self.norms[id(t)][1]) if t is not None else None
        self.rows.append([self.workload, method, config, seed, obs, metrics.fit_models(truth, model) if truth is not None else None, None, None, seconds, passes, (getattr(model, 'stats', None) or {}).get('iterations')])
        return model

    def note(self, method: str, config: str, seed: int = 0, **values) -> None:
        names = ("fit_obs", "fit_truth", "sir_db", "accuracy", "seconds", "passes", "iterations")
        self.rows.append([self.workload, method, config, seed, *[values.get(n) for n in names]])

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(r) for r in self.rows], SCHEMA)


#: The published stopping rule, for every method alike.
STOP = {"max_iter": 1000, "tol": 1e-6}


def _form(t, ranks, p=10, seed=1, **options):
    return tucker.sketch_tucker(t, ranks, p, "two_sweep", seed=seed, **options)


def w1_snr_routes(spark, sf_dir, size=20, order=4, rank=5, snrs=(-20, -10, 0, 10, 20), seeds=(0,), max_iter=60):
    """Fit against SNR of the direct, compressed and core-then-lift routes."""
    log = Log("w1")
    fs = synth.normal_factors(spark, sf_dir, order, size, rank)
    for snr in snrs:
        for s in seeds:
            t, truth = synth.cp_tensor(spark, fs, snr, seed=100 + s)
            t, dense = t.kept(), None
            dense = cp.DenseSource(t.dense())
            config = f"{size}^{order} R={rank} snr={snr}"
            log.run("direct_als", config, s, lambda: cp.fit_cp(dense, rank, "als", seed=s, max_iter=max_iter), t, truth, False)
            form = _form(t, [rank] * order, seed=s)
            log.run("compressed_als", config, s, lambda: cp.compressed_cp(form, rank, seed=s, max_iter=max_iter), t, truth, False)
            log.run("core_then_lift", config, s, lambda: cp.core_then_lift_cp(form, rank, seed=s, max_iter=max_iter), t, truth, False)
    return log.frame(spark)


def w2_sketch_fit(spark, sf_dir, size=100, rank=5, p=5, snrs=(0, 10, 20), seeds=(0,), sweeps=(2,)):
    """Fit against noise of the sequential and two-sweep sketches, truncated to the rank, and of the HOSVD of that rank."""
    log = Log("w2")
    for snr in snrs:
        for s in seeds:
            t, truth = synth.tucker_tensor(spark, sf_dir, size, rank, snr, seed=200 + s)
            t, config = t.kept(), f"{size}^3 R={rank} p={p} snr={snr}"
            log.run("sequential", config, s, lambda: tucker.sketch_tucker(t, [rank] * 3, p, "sequential", seed=s + 1, truncate=True), t, truth)
            for k in sweeps:
                log.run("two_sweep" if k == 2 else f"sweeps_{k}", config, s, lambda: tucker.sketch_tucker(t, [rank] * 3, p, "two_sweep", k, seed=s + 1, truncate=True), t, truth)
            log.run("two_sweep_power", config, s, lambda: tucker.sketch_tucker(t, [rank] * 3, p, "two_sweep", seed=s + 1, truncate=True, power=1), t, truth)
            log.run("hosvd", config, s, lambda: tucker.hosvd(t, [rank] * 3), t, truth)
    return log.frame(spark)


def w3_cp_table(spark, sf_dir, configs=((3, 60, 5),), snr=10.0, seeds=(0,), direct=True, replicas=True, p=10, sweeps=2, generated=False):
    """CP methods at one SNR: fit to the truth, seconds and iterations under one stopping rule.

    generated: factors are drawn from counters, not read from the tables."""
    log = Log("w3")
    for order, size, rank in configs:
        fs = synth.drawn_factors(order, size, rank) if generated else synth.normal_factors(spark, sf_dir, order, size, rank)
        for s in seeds:
            t, truth = synth.cp_tensor(spark, fs, snr, seed=300 + s)
            t, config = t.kept(), f"N={order} I={size} R={rank} snr={snr}"
            log.run("two_sweep_compression", config, s, lambda: _form(t, [rank] * order, p, seed=s + 1), t, truth)
            form = log.run("two_sweep_power_compression", config, s, lambda: _form(t, [rank] * order, p, seed=s + 1, power=1), t, truth)
            log.run("compressed_als", config, s, lambda: cp.compressed_cp(form, rank, seed=s + 1, **STOP), t, truth, False)
            log.run("compressed_als_best_of_5", config, s, lambda: cp.compressed_cp(form, rank, seed=s + 1, n_starts=5, **STOP), t, truth, False)
            log.run("core_then_lift", config, s, lambda: cp.core_then_lift_cp(form, rank, seed=s + 1, **STOP), t, truth, False)
            if direct:
                dense = cp.DenseSource(t.dense())
                log.run("direct_als", config, s, lambda: cp.fit_cp(dense, rank, "als", seed=s + 1, **STOP), t, truth, False)
                log.run("svd_start_extrapolated_als", config, s, lambda: cp.fit_cp(dense, rank, "als", init="svd", extrapolate=True, **STOP), t, truth, False)
            if sweeps and s == seeds[0]:
                log.run(f"direct_als_{sweeps}_sweeps_of_passes", config, s, lambda: cp.cp_als(t, rank, seed=s + 1, max_iter=sweeps), t, truth)
                log.run(f"reuse_als_{sweeps}_sweeps_of_passes", config, s, lambda: cp.cp_als(t, rank, "reuse", seed=s + 1, max_iter=sweeps), t, truth)
            if replicas:
                log.run("anchored_replicas", config, s, lambda: baselines.anchored_replica_cp(t, rank, seed=s + 1), t, truth)
    return log.frame(spark)


def w4_nonneg_table(spark, sf_dir, configs=((3, 60, 5),), snr=10.0, seeds=(0,), direct=("mu", "hals"), p=10, generated=False):
    """Nonnegative CP methods: multiplicative and column-wise updates, direct and compressed, under one stopping rule.

    generated: factors are drawn from counters, not read from the tables."""
    log = Log("w4")
    for order, size, rank in configs:
        fs = synth.drawn_factors(order, size, rank, "exponential") if generated else synth.exponential_factors(spark, sf_dir, order, size, rank)
        for s in seeds:
            t, truth = synth.cp_tensor(spark, fs, snr, seed=400 + s)
            t, config = t.kept(), f"N={order} I={size} R={rank} snr={snr}"
            log.run("two_sweep_compression", config, s, lambda: _form(t, [rank] * order, p, seed=s + 1), t, truth)
            form = log.run("two_sweep_power_compression", config, s, lambda: _form(t, [rank] * order, p, seed=s + 1, power=1), t, truth)
            dense = cp.DenseSource(t.dense()) if direct else None
            for update in ("mu", "hals"):
                log.run(f"compressed_{update}", config, s, lambda: cp.compressed_cp(form, rank, update, seed=s + 1, **STOP), t, truth, False)
                if update in direct:
                    log.run(f"direct_{update}", config, s, lambda: cp.fit_cp(dense, rank, update, init="uniform", seed=s + 1, **STOP), t, truth, False)
    return log.frame(spark)


def _slopes(log: Log, sizes: Sequence[int]) -> None:
    """For each method the exponent of a power law through its seconds (in the column of seconds)."""
    for method in dict.fromkeys(r[1] for r in log.rows):
        own = {int(r[2].split("=")[1]): r[8] for r in log.rows if r[1] == method}
        if len(own) == len(sizes):
            log.note(f"{method}_slope", f"sizes {min(sizes)} to {max(sizes)}", seconds=metrics.log_slope(list(own), [max(x, 1e-6) for x in own.values()]))


def w5_scaling_in_memory(spark, sf_dir, sizes=(40, 80, 120, 160), rank=5, p=15, iters=5):
    """Seconds against size with the data at hand, and their slopes; one direct method is timed for a few iterations."""
    log = Log("w5")
    for size in sizes:
        t, truth = synth.cp_tensor(spark, synth.normal_factors(spark, sf_dir, 3, size, rank), 10, seed=5)
        t, config = t.kept(), f"I={size}"
        form = log.run("two_sweep_compression", config, 0, lambda: _form(t, [rank] * 3, p), t, truth)
        log.run("compressed_als", config, 0, lambda: cp.compressed_cp(form, rank, max_iter=200, tol=0), t, truth, False)
        dense = cp.DenseSource(t.dense())
        log.run(f"direct_als_{iters}_iterations", config, 0, lambda: cp.fit_cp(dense, rank, "als", max_iter=iters, tol=0), t, truth, False)
    _slopes(log, sizes)
    return log.frame(spark)


def w6_scaling_compact(spark, sf_dir, sizes=(1_000, 10_000, 100_000, 300_000), rank=5, updates=("als", "mu", "hals"), max_iter=20):
    """Seconds against size when only the Tucker form exists, and their slopes: nothing of the full size is ever made."""
    log = Log("w6")
    from .functions.counter import uniform

    for size in sizes:
        fs = [uniform(60 + n, np.ix_(np.arange(size), np.arange(rank))) for n in range(3)]
        form, truth = tucker.TuckerModel.from_cp(fs), cp.CPModel(fs)
        for update in updates:
            log.run(f"compressed_{update}", f"I={size}", 0, lambda: cp.compressed_cp(form, rank, update, max_iter=max_iter, tol=0), None, truth)
    _slopes(log, sizes)
    return log.frame(spark)


def w7_huge_nonneg(spark, sf_dir, size=None, order=4, rank=10, max_iter=2000, seed=1, generated=False):
    """A huge nonnegative tensor given in rotated Tucker form: recover it, and see what lifting a core's CP would give.

    size: as long as all events reach, unless given. generated: exponential factors drawn by what stands in the orders, as long as all
    orders reach, instead of the events' values.
    """
    log = Log("w7")
    if generated:
        fs = synth.order_factors(spark, sf_dir, order, rank)
        size = len(fs[0])
    else:
        size = size or tables.table(spark, sf_dir, "events").count() // (order * rank)
        fs = synth.exponential_factors(spark, sf_dir, order, size, rank, zeros=5)
    form = tucker.TuckerModel.from_cp(fs).rotate([orth(np.random.default_rng(n).standard_normal((rank, rank)), "qr") for n in range(order)])
    truth, config = cp.CPModel(fs), f"{size}^{order} R={rank}"
    model = log.run("compressed_hals", config, seed, lambda: cp.compressed_cp(form, rank, "hals", seed=seed, max_iter=max_iter, tol=0, n_starts=1), None, truth)
    log.rows[-1][6] = float(np.mean([metrics.sir(a, b).mean() for a, b in zip(fs, model.factors, strict=True)]))
    lifted = log.run("core_then_lift", config, seed, lambda: cp.core_then_lift_cp(form, rank, seed=seed, max_iter=200), None, truth)
    log.note("core_then_lift_negative_share", config, seed, accuracy=float(np.mean([(f * np.sign(f.sum(0)) < -1e-6).mean() for f in lifted.factors])))
    return log.frame(spark)


#: Of a block of documents (arrays beyond half a region of the JVM's heap stay there until a full collection), of the blocks that a
#: worker gets at once, and blocks that Spark's reader has in memory.
BLOCK_BYTES, SENT_BYTES, READ_BLOCKS = 400_000, 2 << 20, 16


def _text_tensor(spark, sf_dir, grid: Sequence[int] = (1, 1, 1)) -> tuple[BlockTensor, DataFrame]:
    """Document x character x next character, rows of a document summing to one; i and language. Blocks are cut along the
    documents only, into as many as the grid says or as memory needs, and each is filled from one packed row a document."""
    docs = tables.table(spark, sf_dir, "documents")
    rows = tables.stored(tables.bigram_rows(docs, "doc_id"))
    ids = tables.stored(tables.dictionary(rows, "id", True))
    labels = ids.join(docs.select(F.col("doc_id").alias("key"), F.col("lang").alias("label")), "key").select(F.col("idx").alias("i"), "label")
    size, side = ids.count(), tables.LETTERS
    step = max(1, ceil(size / max(grid[0], plan_grid((size, side, side), *[BLOCK_BYTES] * (size > tall.TALL_ROWS))[0])))

    def fill(group: pd.DataFrame) -> pd.DataFrame:
        first = int(group["_b"].iloc[0]) * step
        data = np.zeros((min(step, size - first), side * side))
        for i, own in zip(group["i"], group["own"], strict=True):
            p, n = tables.merged(own)
            data[i - first, p] = n / n.sum()
        return pd.DataFrame({"lo": [[first, 0, 0]], "dims": [[len(data), side, side]], "data": [data.tobytes()]})

    block = F.floor(F.col("i") / step)
    placed = rows.join(ids.withColumnRenamed("key", "id"), "id").select(F.col("idx").alias("i"), "own")
    blocks = placed.withColumn("_b", block).groupBy("_b").applyInPandas(fill, BLOCK)
    return BlockTensor(blocks, (size, side, side), tall=0 if size > tall.TALL_ROWS else None), tables.stored(labels)


def _accuracy(spark, features: np.ndarray, labels: DataFrame, k: int, plane: bool = False) -> float:
    unit = lambda x: x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    x = features.mapped(unit) if isinstance(features, tall.Tall) else unit(features)
    found = cluster.kmeans(spark, cluster.plane(x) if plane else x, k)
    return cluster.cluster_accuracy(found.join(labels, "i"))


def w8_text_clustering(spark, sf_dir, **options):
    """Cluster documents by the first-mode factor of seven forms; the truth is their language. plane: forms that are clustered
    in the plane of a t-SNE too (of up to 3,000 rows; beyond that in the plane of two principal components)."""
    with setting(spark, "spark.sql.execution.arrow.maxBytesPerBatch", str(SENT_BYTES)):
        t, labels = _text_tensor(spark, sf_dir, options.get("grid", (4, 1, 1)))
        t = t.kept()
        with setting(spark, "spark.sql.parquet.columnarReaderBatchSize", str(READ_BLOCKS)):
            return _text_clustering(spark, t, labels, **options)


def _text_clustering(spark, t, labels, ranks=(10, 10, 10), sizes=(20, 15, 15), grid=(4, 1, 1), plane=(), max_iter=100):
    log = Log("w8")
    k = labels.select("label").distinct().count()
    total = labels.count()
    log.note("largest_class", "share", accuracy=labels.groupBy("label").count().agg(F.max("count")).first()[0] / total)
    config = f"ranks {ranks} sketched {sizes} grid {grid}"
    wide = [s - r for s, r in zip(sizes, ranks, strict=True)]
    forms = {
        "tucker_als": log.run("tucker_als", config, 0, lambda: tucker.tucker_als(t, ranks, 2), t),
        "two_sweep": log.run("two_sweep", config, 0, lambda: tucker.sketch_tucker(t, ranks, max(wide), "two_sweep"), t),
        "sequential": log.run("sequential", config, 0, lambda: tucker.sketch_tucker(t, ranks, max(wide), "sequential", mode_order=(0, 1, 2)), t),
    }
    for name in ("tucker_als", "two_sweep"):
        forms[f"compressed_ntd_on_{name}"] = log.run(f"compressed_ntd_on_{name}", config, 0, lambda: ntd.compressed_ntd(forms[name], ranks, max_iter=max_iter), t, None, False)
        forms[f"compressed_hals_on_{name}"] = log.run(f"compressed_hals_on_{name}", config, 0, lambda: cp.compressed_cp(forms[name], ranks[0], "hals", max_iter=max_iter), t, None, False)
    for row in list(log.rows):
        if row[1] in forms:
            model = forms[row[1]]
            features = model.absorbed(0)[0] if isinstance(model, cp.CPModel) else model.features(0)
            row[7] = _accuracy(spark, features, labels, k)
            if row[1] in plane:
                log.note(f"{row[1]}_in_the_plane", config, accuracy=_accuracy(spark, features, labels, k, True))
    return log.frame(spark)


def w8_control(spark, sf_dir):
    """Negative control: labels of the embeddings carry no signal."""
    log = Log("w8_control")
    t = tables.embedding_cells(spark, sf_dir).to_blocks((2, 1, 1)).kept()
    labels = tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("i"), "label")
    form = log.run("two_sweep", "8x8 per vector", 0, lambda: tucker.sketch_tucker(t, (20, 8, 8), 5, "two_sweep"), t)
    log.rows[-1][7] = _accuracy(spark, form.features(0), labels, 10)
    return log.frame(spark)


def w9_two_stage(spark, sf_dir, facts="five_way", rank=10, max_iter=200):
    """A dense table tensor: sketch it in stage one, decompose the form with and without nonnegativity in stage two."""
    log = Log("w9")
    f, modes, value = getattr(tables, facts)(spark, sf_dir)
    t, dictionaries = tables.from_table(f, modes, value)
    t = t.to_blocks([2, *[1] * (t.order - 1)]).kept()
    for r in (1, 3, rank):
        form = log.run("two_sweep", f"{facts} ranks {r}", 0, lambda: _form(t, [min(r, s) for s in t.shape], 5), t)
    log.run("compressed_als", f"{facts} R={rank}", 0, lambda: cp.compressed_cp(form, rank, max_iter=max_iter), t, None, False)
    hals = log.run("compressed_hals", f"{facts} R={rank}", 0, lambda: cp.compressed_cp(form, rank, "hals", max_iter=max_iter), t, None, False)
    log.run("direct_als_one_iteration", f"{facts} R={rank}", 0, lambda: cp.cp_als(t, rank, max_iter=1), t)
    # Samples of the last mode are clustered by its factor; the truth of a month is its year.
    last, keys = list(dictionaries.items())[-1]
    years = keys.select(F.col("idx").alias("i"), F.substring(F.col("key").cast("string"), 1, 4).alias("label"))
    k = years.select("label").distinct().count()
    # With as many clusters as samples there would be nothing to find.
    for name, features in () if t.shape[-1] <= 2 * k else (("two_sweep", form.features(t.order - 1)), ("compressed_hals", hals.absorbed(t.order - 1)[-1])):
        log.note(f"{name}_clusters_of_{last}", f"{facts} R={rank} k={k}", accuracy=_accuracy(spark, features, years, k))
    return log.frame(spark)


def w10_sparse(spark, sf_dir, rank=5):
    """A hyper-sparse tensor: the planner avoids products that would grow it; column-wise CP touches nonzeros only."""
    log = Log("w10")
    f, modes, value = tables.activity(spark, sf_dir)
    t, _ = tables.from_table(f, modes, value, "count", ["user"])
    t = t.kept()
    plan = cost.choose(t.df, t.shape, [rank + 5] * 3)
    form = log.run(f"{plan.method}_{plan.layout}", plan.why, 0, lambda: tucker.sketch_tucker(t, [rank] * 3, 5, plan.method), t)
    log.run("compressed_hals", f"R={rank}", 0, lambda: cp.compressed_cp(form, rank, "hals", max_iter=200), t, None, False)
    log.run("columnwise_als", f"R={rank}", 0, lambda: cp.cp_als(t, rank, "columnwise", max_iter=2), t)
    return log.frame(spark)


def w11_replica_noise(spark, sf_dir, size=40, rank=5):
    """Anchored replicas without noise and at 10 dB."""
    log = Log("w11")
    fs = synth.normal_factors(spark, sf_dir, 3, size, rank)
    for snr in (None, 10.0):
        t, truth = synth.cp_tensor(spark, fs, snr, seed=11)
        t = t.kept()
        log.run("anchored_replicas", f"snr={snr}", 0, lambda: baselines.anchored_replica_cp(t, rank), t, truth)
    return log.frame(spark)


def w12_grids(spark, sf_dir, size=40, rank=5, grids=((1, 1, 1), (2, 4, 3), (1, 1, 4))):
    """The same seed over different grids, eager and lazy: the same result."""
    log = Log("w12")
    fs = synth.normal_factors(spark, sf_dir, 3, size, rank)
    for grid in grids:
        t, truth = synth.cp_tensor(spark, fs, 10, grid, seed=12)
        t = t.kept()
        for reduce in ("eager", "lazy"):
            log.run(f"sequential_{reduce}", f"grid {grid}", 0, lambda: tucker.sketch_tucker(t, [rank] * 3, 5, "sequential", reduce=reduce), t, truth)
        log.run("two_sweep", f"grid {grid}", 0, lambda: tucker.sketch_tucker(t, [rank] * 3, 5, "two_sweep"), t, truth)
    return log.frame(spark)


def w13_random_numbers(spark, sf_dir, size=60, rank=5):
    """Random test matrices sent or regenerated: the same quality, bytes told apart (in the passes of the config)."""
    log = Log("w13")
    t, truth = synth.tucker_tensor(spark, sf_dir, size, rank, 10, seed=13)
    for omega in ("counter", "broadcast"):
        x = t.kept()
        log.run(omega, f"I={size}", 0, lambda: tucker.sketch_tucker(x, [rank] * 3, 5, "sequential", omega=omega), x, truth)
        log.note(f"{omega}_megabytes_sent", f"I={size}", accuracy=x.passes.broadcast_bytes / 1e6)
    return log.frame(spark)


def w14_sampling(spark, sf_dir, size=40, rank=3, snr=10.0):
    """Sampled Tucker methods beside sketched ones under noise."""
    log = Log("w14")
    t, truth = synth.tucker_tensor(spark, sf_dir, size, rank, snr, seed=14)
    t = t.kept()
    c = t.to_cells().kept()
    config = f"{size}^3 R={rank} snr={snr}"
    log.run("two_sweep", config, 0, lambda: tucker.sketch_tucker(t, [rank] * 3, 5, "two_sweep"), t, truth)
    log.run("entry_sampled", config, 0, lambda: tucker.entry_sample_tucker(c, [rank] * 3, 0.1, init="random", iters=1), c, truth)
    log.run("fiber_sampled", config, 0, lambda: tucker.fiber_sample_tucker(c, [rank] * 3, 12), c, truth)
    return log.frame(spark)


WORKLOADS: dict[str, Callable[..., DataFrame]] = {f.__name__: f for f in (w1_snr_routes, w2_sketch_fit, w3_cp_table, w4_nonneg_table, w5_scaling_in_memory, w6_scaling_compact, w7_huge_nonneg, w8_text_clustering, w8_control, w9_two_stage, w10_sparse, w11_replica_noise, w12_grids, w13_random_numbers, w14_sampling)}


def monte_carlo_table(frame: DataFrame, by: Sequence[str] = ("workload", "config", "method")) -> DataFrame:
    """Mean and deviation over seeds, and runs whose fit to the truth is below a half."""
    return frame.groupBy(*by).agg(F.avg("fit_truth").alias("mean_fit"), F.stddev_samp("fit_truth").alias("sd_fit"), F.avg("seconds").alias("mean_seconds"), F.avg("iterations").alias("mean_iterations"), F.count("*").alias("runs"), F.sum((F.col("fit_truth") < 0.5).cast("int")).alias("failures"))


