"""Kernels against dense numpy, and the conventions that everything relies on."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from multiway.functions import counter
from multiway.operators import algebra as A
from multiway.operators import index as X
from multiway.operators.cluster import assignment
from multiway.operators.constraints import nonneg, soft
from multiway.operators.cp import updated
from multiway.operators.orth import orth, orth_error, orth_rows, subspace_distance


def test_worked_grid_example():
    # Grid 2 x 4 x 3: worker 13 is block (1, 3, 2) and stands at (3, 3) of the mode-2 unfolding.
    assert [c + 1 for c in X.ind2sub(12, (2, 4, 3))] == [1, 3, 2]
    assert X.resource_matrix((2, 4, 3), 1)[2, 2] == 13


@given(st.lists(st.integers(1, 5), min_size=2, max_size=4), st.data())
@settings(max_examples=30, deadline=None)
def test_linear_index_round_trip(shape, data):
    i = data.draw(st.integers(0, int(np.prod(shape)) - 1))
    assert X.sub2ind(X.ind2sub(i, shape), shape) == i


@pytest.mark.parametrize("shape", [(3, 4), (3, 4, 5), (2, 3, 4, 5)])
def test_mttkrp_forms_agree(shape):
    random = np.random.default_rng(0)
    x, fs = random.standard_normal(shape), [random.standard_normal((s, 3)) for s in shape]
    shared = A.shared_mttkrp(x, fs)
    for n in range(len(shape)):
        want = A.unfold_dense(x, n) @ A.khatri_rao(fs, skip=n)
        for how in ("explicit", "contract", "columnwise"):
            assert np.allclose(A.core_mttkrp(x, fs, n, how), want)
        assert np.allclose(shared[n], want)
        assert np.allclose(A.fold_dense(A.unfold_dense(x, n), shape, n), x)
    assert np.allclose(A.unfold_dense(A.cp_dense(fs), 0), fs[0] @ A.khatri_rao(fs, skip=0).T)


def test_counter_numbers_are_the_same_everywhere(spark):
    rows = spark.range(50).select("id", (F.col("id") * 37 % 11).alias("b"), counter.mix_col(9, [F.col("id"), F.col("id") * 37 % 11]).alias("h"), counter.gauss_col(9, [F.col("id")]).alias("g")).collect()
    i = np.array([r["id"] for r in rows])
    assert [r["h"] for r in rows] == counter.mix(9, [i, i * 37 % 11]).tolist()
    assert np.allclose([r["g"] for r in rows], counter.gauss(9, [i]))
    x = counter.gauss(3, np.ix_(np.arange(300), np.arange(300)))
    assert abs(x.mean()) < 0.02 and abs(x.std() - 1) < 0.02


@pytest.mark.parametrize("how", ["gram", "qr"])
def test_orthonormal_bases(how):
    random = np.random.default_rng(1)
    z = random.standard_normal((60, 8)) @ np.diag(10.0 ** -np.arange(0, 4, 0.5))
    assert orth_error(orth(z, how)) < 1e-8
    low = z[:, :3] @ random.standard_normal((3, 8))
    assert orth(low, how).shape == (60, 3)


@pytest.mark.parametrize("how", ["gram", "tsqr"])
def test_orthonormal_rows(spark, how):
    z = np.random.default_rng(2).standard_normal((80, 5))
    rows = orth_rows(A.rows_frame(spark, z).repartition(3), how).orderBy("i").collect()
    u = np.array([r["f"] for r in rows])
    assert orth_error(u) < 1e-8 and subspace_distance(u, orth(z)) < 1e-6


def test_update_rules_reduce_the_error():
    random = np.random.default_rng(3)
    fs = [random.random((s, 3)) for s in (8, 9, 10)]
    x = A.cp_dense([random.random((s, 3)) for s in (8, 9, 10)])
    q, t = A.core_mttkrp(x, fs, 0), A.gram_hadamard([f.T @ f for f in fs], 0)
    error = lambda a: float(((x - A.cp_dense([a, *fs[1:]])) ** 2).sum())
    for update in ("als", "mu", "hals", "pg"):
        a = updated(fs[0], q, t, update, nonneg())
        assert error(a) < error(fs[0]) and (a >= 0).all()


def test_increment_only_clipping_could_never_shrink():
    """Clipping the increment instead of the entry leaves entries that only grow; ours may fall."""
    a, q, t = np.array([[5.0]]), np.array([[1.0]]), np.array([[1.0]])
    assert updated(a, q, t, "hals", nonneg())[0, 0] == 1.0


def test_soft_threshold_at_its_edges():
    x = np.array([-3.0, -2.0, 0.0, 2.0, 3.0])
    assert soft(2)(x).tolist() == [-1, 0, 0, 0, 1]
    assert (nonneg() & soft(2))(x).tolist() == [0, 0, 0, 0, 1]


def test_assignment_is_optimal():
    from itertools import permutations

    cost = np.random.default_rng(4).random((5, 6))
    best = min(sum(cost[i, p[i]] for i in range(5)) for p in permutations(range(6), 5))
    assert np.isclose(cost[np.arange(5), assignment(cost)].sum(), best)


def test_drawn_factors_are_fixed_and_have_the_planted_shape():
    from multiway.sources import synth

    a, b = synth.drawn_factors(3, 400, 5), synth.drawn_factors(3, 400, 5)
    assert all((x == y).all() for x, y in zip(a, b, strict=True)) and not (a[0] == a[1]).any()
    assert abs(np.mean(a)) < 0.1 and abs(np.std(a) - 1) < 0.1
    e = np.array(synth.drawn_factors(3, 400, 5, "exponential"))
    zero = e == 0
    assert (e >= 0).all() and abs(zero.mean() - 0.1) < 0.02 and abs(e[~zero].mean() - 10) < 1


def test_planted_blocks_stay_small(spark):
    from multiway.sources import synth

    t, _ = synth.cp_tensor(spark, synth.drawn_factors(3, 500, 2))
    assert t.df.rdd.getNumPartitions() == 32
    t, truth = synth.cp_tensor(spark, synth.drawn_factors(3, 12, 2))
    assert t.df.rdd.getNumPartitions() == 4
    assert abs(t.norm2() - (np.einsum("ir,jr,kr->ijk", *truth.factors) ** 2).sum()) < 1e-6


def test_bigrams_of_odd_texts_and_repeated_ids(spark):
    from pyspark.sql import functions as F

    from multiway.sources.tables import bigrams

    rows = [(1, "Abéz"), (1, "ab"), (None, "xy"), (None, "XY€\U0001f600"), (2, ""), (3, None), (4, "q"), (5, "z" * 70_000)]
    docs = spark.createDataFrame(rows, "doc_id int, text string").repartition(3)
    want: dict = {}
    for k, t in rows:
        c = ["abcdefghijklmnopqrstuvwxyz".find(x) % 27 for x in (t or "").lower()]
        for pair in zip(c, c[1:]):
            want[k, *pair] = want.get((k, *pair), 0) + 1
    got = bigrams(docs, "doc_id")
    assert {(r["id"], r["a"], r["b"]): r["n"] for r in got.collect()} == want and got.schema["id"].dataType.simpleString() == "int"
    plan = got.select(F.col("id"))._jdf.queryExecution().toString()
    assert "Generate explode" not in plan  # characters don't become rows
