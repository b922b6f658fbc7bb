"""Whole methods on planted tensors."""

import numpy as np
import pytest

from multiway.operators import cp, metrics, ntd, tucker
from multiway.operators.constraints import nonneg
from multiway.sources import synth


@pytest.fixture(scope="module")
def planted(spark, sf):
    fs = synth.normal_factors(spark, sf, 3, 18, 3)
    t, truth = synth.cp_tensor(spark, fs, None, (2, 1, 1))
    t = t.kept()
    return t, t.to_cells().kept(), truth


def test_layouts_and_grids_agree(planted):
    t, cells, truth = planted
    fs = truth.factors
    other = cells.to_blocks((2, 3, 2))
    for n in range(3):
        for call in (lambda x: x.mttkrp(fs, n), lambda x: x.sketch(n, 4, 3), lambda x: x.project(n, fs), lambda x: x.gram(n)):
            assert np.allclose(call(t), call(cells)) and np.allclose(call(t), call(other))


def test_sketches_recover_and_count_their_passes(planted):
    t, _, truth = planted
    for method, reads in (("sequential", 3 + 3), ("two_sweep", 6)):
        form = tucker.sketch_tucker(t, (3, 3, 3), 5, method)
        assert form.ranks == (3, 3, 3)  # oversampling finds no more than there is
        assert metrics.fit_models(truth, form) > 1 - 1e-6 and form.stats["passes"] <= reads
    lazy = tucker.sketch_tucker(t, (3, 3, 3), 5, "sequential", reduce="lazy")
    assert np.allclose(lazy.dense(), truth.dense())


def test_compressed_equals_direct_from_the_same_start(planted):
    t, _, _ = planted
    form = tucker.hosvd(t, (3, 3, 3))
    start = cp.initial(t.shape, 3, "normal", 5)
    a = cp.fit_cp(t, 3, "als", init=start, max_iter=2, tol=0)
    b = cp.compressed_cp(form, 3, init=start, max_iter=2, tol=0)
    assert np.allclose(a.dense(), b.dense(), atol=1e-6)


def test_constraints_hold_for_the_factors_themselves(spark, sf):
    fs = synth.exponential_factors(spark, sf, 3, 18, 3)
    form = tucker.TuckerModel.from_cp(fs)
    for update in ("hals", "mu"):
        model = cp.compressed_cp(form, 3, update, max_iter=300)
        assert all((f >= 0).all() for f in model.factors) and model.history[-1] > 0.95
    with pytest.raises(ValueError, match="constraint"):
        cp.core_then_lift_cp(form, 3, nonneg())
    with pytest.raises(ValueError, match="nonnegative"):
        cp.fit_cp(cp.TuckerSource(form), 3, "mu", constraint={0: nonneg()})
    assert ntd.compressed_ntd(form, (3, 3, 3), max_iter=300).stats["history"][-1] > 0.95


def test_measures(spark, sf):
    a = np.random.default_rng(0).standard_normal((50, 3))
    assert metrics.sir(a, -3 * a[:, [2, 0, 1]]).min() > 200
    model = cp.CPModel([a, a + 1, a - 1])
    assert abs(metrics.fit_models(model, model.normalise()) - 1) < 1e-6
    form = tucker.TuckerModel.from_cp(model.factors)
    assert abs(metrics.model_inner(form, model) - model.norm2()) < 1e-6 * model.norm2()
    turned = form.rotate([np.linalg.qr(np.random.default_rng(n).standard_normal((3, 3)))[0] for n in range(3)])
    assert np.allclose(turned.dense(), form.dense())


def test_guards(planted):
    t, _, _ = planted
    with pytest.raises(ValueError, match="unknown method"):
        tucker.sketch_tucker(t, (2, 2, 2), method="none")


def test_tensor_calls_plan_partial_sums(spark, sf):
    from multiway.catalog.base import built
    from multiway.operators.algebra import formula_rows, mttkrp

    t = built(spark, sf, "business")[0]
    plan = mttkrp(t.df, [formula_rows(spark, s, 3) for s in t.shape], 0, 3)._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "CartesianProduct" not in plan


def test_entry_and_queries(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_bases_of_long_modes_stay_rows(spark, monkeypatch):
    """Beyond what the driver may hold the gathered sketch refuses, and the row-wise one goes on."""
    import numpy as np
    import pytest

    from multiway.operators import tensors, tucker
    from multiway.operators.orth import gram_rows

    random = np.random.default_rng(0)
    x = np.einsum("ar,br,cr->abc", *(random.standard_normal((s, 2)) for s in (40, 9, 8)))
    rows = [(a, b, c, float(x[a, b, c])) for a in range(40) for b in range(9) for c in range(8)]
    t = tensors.CooTensor(spark.createDataFrame(rows, "i1 long, i2 long, i3 long, v double"), x.shape)
    monkeypatch.setattr(tensors, "DRIVER_NUMBERS", 150)
    with pytest.raises(ValueError, match="row-wise"):
        tucker.sketch_tucker(t, [2, 2, 2], 2, "two_sweep")
    bases, core = tucker.sketch_tucker_rows(t, [2, 2, 2], 2)
    assert all(np.allclose(gram_rows(b), np.eye(core.shape[n])) for n, b in enumerate(bases))
    assert np.isclose((core**2).sum(), (x**2).sum())


def test_power_steps_add_no_pass(spark):
    import numpy as np

    from multiway.functions.counter import gauss
    from multiway.operators import tucker
    from multiway.sources import synth

    fs = [gauss(n, np.ix_(np.arange(30), np.arange(3))) for n in range(3)]
    plain, truth = synth.cp_tensor(spark, fs, 5.0)
    t = plain.kept()
    one, two = (tucker.sketch_tucker(t, [3] * 3, 4, "two_sweep", power=k) for k in (0, 1))
    assert one.stats["passes"] == two.stats["passes"] and two.fit() > one.fit()


def test_event_factors_travel_as_columns(spark, sf, monkeypatch):
    from multiway.sources.synth import exponential_factors, placed

    rows = {r["event_id"]: r["value"] for r in spark.read.parquet(f"{sf}/events.parquet").select("event_id", "value").collect()}
    monkeypatch.setattr("pyspark.sql.classic.dataframe.DataFrame.collect", lambda self: pytest.fail("row objects on the driver"))
    fs = exponential_factors(spark, sf, 2, 40, 5)
    want = np.array([rows[k] / 5 for k in range(400)]).reshape(2, 40, 5)
    assert all(((f == 0) | np.isclose(f, w)).all() and (f == 0).mean() < 0.2 for f, w in zip(fs, want, strict=True))
    for places in ([0, 1, 1], [0, 1], [0, 1, 3], [0, 1, -1]):
        with pytest.raises(ValueError):
            placed(spark.createDataFrame([(k, 1.0) for k in places], "k long, v double"), 3)


def test_column_sweeps_in_blocks_equal_plain_ones(monkeypatch):
    monkeypatch.setattr(cp, "BLOCK_ROWS", 7)
    random = np.random.default_rng(3)
    form = tucker.TuckerModel.from_cp([random.exponential(size=(s, 3)) for s in (20, 15, 9)])
    got, want = cp.compressed_cp(form, 3, "hals", max_iter=25, tol=0), cp.fit_cp(cp.TuckerSource(form), 3, "hals", init="uniform", max_iter=25, tol=0)
    assert np.allclose(got.history, want.history) and got.stats["iterations"] == 25
    assert all(np.allclose(a, b) for a, b in zip(got.factors, want.factors, strict=True))


def test_long_mode_by_the_gram_of_the_columns(planted, monkeypatch):
    from multiway.operators import tensors

    t, cells, _ = planted
    want, fit = tucker.hosvd(t, (2, 3, 3)), tucker.tucker_als(t, (2, 3, 3)).fit()
    blocks = cells.to_blocks((3, 1, 1)).kept()
    for limit in (18**2 - 1, 18 * 9 - 1):  # a Gram of 18 rows, then a projection of 18 x 9, is too large
        monkeypatch.setattr(tucker, "DRIVER_NUMBERS", limit)
        got = tucker.tucker_als(blocks, (2, 3, 3))
        assert abs(got.fit() - fit) < 1e-8
    u = blocks.leading(0, 2)
    assert np.allclose(u @ u.T, want.factors[0] @ want.factors[0].T, atol=1e-6) and np.allclose(u.T @ u, np.eye(2))
    assert cells.to_blocks((1, 2, 1)).leading(0, 2) is None
    monkeypatch.setattr(tensors, "DRIVER_NUMBERS", 18**2)
    assert np.allclose(cells.to_blocks((2, 3, 1)).gram(1), t.gram(1)) and np.allclose(blocks.gram(2), t.gram(2))


def test_text_tensor_in_blocks_equals_its_cells(spark, sf):
    from multiway import workloads as W
    from multiway.sources import tables

    t, labels = W._text_tensor(spark, sf, (3, 1, 1))
    counts = tables.bigrams(tables.table(spark, sf, "documents"), "doc_id").collect()
    ids = {k: i for i, k in enumerate(sorted({r["id"] for r in counts}))}
    want = np.zeros((len(ids), 27, 27))
    for r in counts:
        want[ids[r["id"]], r["a"], r["b"]] = r["n"]
    assert np.allclose(t.dense(), want / want.sum((1, 2), keepdims=True)) and labels.count() == len(ids)
    assert t.df.count() == 3


def test_kmeans_beyond_twenty_thousand_rows_stays_with_the_best_start(spark):
    import tracemalloc

    from multiway.operators import cluster

    random = np.random.default_rng(2)
    truth = np.arange(30_000) % 5
    x = random.standard_normal((30_000, 40)) * 0.1 + (20 * random.standard_normal((5, 40)))[truth]
    tracemalloc.start()
    own = cluster.lloyd(x, 5)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(set(zip(own, truth))) == 5 and peak < 4 * x.nbytes  # rows x clusters x columns would be 5 x
    found = {r["i"]: r["cluster"] for r in cluster.kmeans(spark, x, 5).collect()}
    assert [found[i] for i in range(30_000)] == own.tolist()


def test_order_factors_are_drawn_by_every_whole_order(spark, tmp_path):
    from multiway.functions.counter import P, mix
    from multiway.sources.synth import _zero, order_factors

    keys = np.random.default_rng(3).permutation(47)
    rows = [(int(k), int(k) % 7, 100.25 + int(k)) for k in keys]
    odd = [(None, 1, 2.0), (50, None, 2.0), (51, 1, None), (52, 1, float("nan")), (53, 1, float("inf"))]
    spark.createDataFrame(rows + odd, "o_orderkey long, o_custkey long, o_totalprice double").repartition(5).write.parquet(f"{tmp_path}/orders.parquet")
    k = np.arange(40)
    v = (-10 * np.log((mix(70, [k, k % 7, 10025 + 100 * k]) + 0.5) / P)).reshape(2, 5, 4)
    v[:, _zero(5, 4, 5)] = 0
    assert np.allclose(order_factors(spark, str(tmp_path), 2, 4), v, rtol=1e-12, atol=0)
    with pytest.raises(ValueError):
        order_factors(spark, str(tmp_path), 4, 12)


def test_tall_factors_in_files_give_the_same_clusters(spark, sf, monkeypatch):
    """Every form of the text workload with document factors in a file of the driver, in blocks, as with whole matrices."""
    from multiway import workloads as W
    from multiway.operators import tall

    sizes = {"ranks": (4, 4, 4), "sizes": (6, 6, 6), "plane": ("two_sweep",), "max_iter": 12}
    want = W.w8_text_clustering(spark, sf, **sizes).collect()
    monkeypatch.setattr(tall, "TALL_ROWS", 150)
    monkeypatch.setattr(tall, "BLOCK_ROWS", 64)
    # Neither a matrix of the documents' rows nor an identity of their number is made on the driver.
    whole, pieces, eye = tall.Tall.gathered, [], np.eye
    monkeypatch.setattr(tall.Tall, "gathered", classmethod(lambda cls, *a: pieces.append(a[1:3]) or whole(*a)))
    monkeypatch.setattr(np, "eye", lambda n, *a, **k: eye(n, *a, **k) if n <= 150 else pytest.fail(f"an identity of {n} rows"))
    got = W.w8_text_clustering(spark, sf, **{**sizes, "plane": ()}).collect()
    assert pieces and all(rows == 200 and width <= 10 for rows, width in pieces)
    by = {r["method"]: r for r in want}
    for r in got:
        w = by[r["method"]]
        assert r["iterations"] == w["iterations"] and (r["passes"] or 0) <= (w["passes"] or 0) + 6
        assert (r["fit_obs"] is None and w["fit_obs"] is None) or abs(r["fit_obs"] - w["fit_obs"]) < 1e-6
        assert abs(r["accuracy"] - w["accuracy"]) < 0.02
    assert len(got) == len(want) - 1


def test_tall_matrix_answers_as_an_array(spark, monkeypatch):
    from multiway.operators import cluster, tall

    monkeypatch.setattr(tall, "BLOCK_ROWS", 16)
    random = np.random.default_rng(4)
    x, w, v = random.standard_normal((50, 4)), random.standard_normal((4, 3)), random.uniform(1, 2, 3)
    a = tall.Tall.made(50, 4, lambda at: x[at])
    b = a @ w
    assert b.shape == (50, 3) and np.allclose(b.whole(), x @ w) and np.allclose(list(b * v), x @ w * v)
    assert np.allclose(b.T @ b, w.T @ x.T @ x @ w) and np.allclose(a.T @ b, x.T @ x @ w) and np.allclose(tall.norms(b / v), np.linalg.norm(x @ w / v, axis=0))
    c = (tall.Tall.made(50, 4, lambda at: x[at]) * np.arange(1.0, 5)).step(b, lambda p, q: p + q[:, :1])
    y = x * np.arange(1, 5) + (x @ w)[:, :1]
    assert np.allclose(c.whole(), y) and np.allclose(c.T @ c, y.T @ y) and np.allclose(b.T @ c, (x @ w).T @ y)
    half = c / np.full(4, 2.0)
    assert np.allclose(half.T @ half, y.T @ y / 4) and np.allclose(half.T @ b, y.T @ x @ w / 2)
    assert (cluster.lloyd(a, 3) == cluster.lloyd(x, 3)).all()
    assert cluster.kmeans(spark, a, 3, driver_rows=20).orderBy("i").toPandas()["cluster"].tolist() == cluster.lloyd(x, 3).tolist()
    p, q = cluster.plane(a, limit=20).whole(), cluster.plane(x, limit=20)
    assert np.allclose(np.abs(p), np.abs(q))
    with pytest.raises(ValueError, match="kernel"):
        a.sent((50, 2, 2))


def test_labels_are_no_row_objects_of_the_driver(spark):
    from multiway.operators import cluster

    key, x = "spark.sql.execution.arrow.localRelationThreshold", np.repeat([[0.0], [5.0]], 30, 0)
    before = spark.conf.get(key, None)
    found = cluster.kmeans(spark, x, 2)
    assert "LocalTableScan" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.count() == 60 and spark.conf.get(key, None) == before
