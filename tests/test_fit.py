from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.conftest import MIDDLE
from vecquant.functions import curves
from vecquant.operators import codec, fit, prep
from vecquant.operators.fit import Search


def test_default_parameters():
    samples, mean_rate, spread_rate = fit.default_hparams(2)
    assert samples == 12 and mean_rate == 1 and abs(spread_rate - 0.7834) < 1e-4
    assert abs(fit.separable_rate(2) - 0.5223) < 1e-4
    u = fit.rank_utilities(12)
    assert abs(u.sum()) < 1e-12 and (np.diff(u) <= 0).all()


@pytest.mark.parametrize("curve", curves.NAMES)
@pytest.mark.parametrize("bits", [8, 4])
def test_search_beats_uniform_and_comes_near_the_grid(vectors, curve, bits):
    from vecquant.plans.workloads import grid_axes

    ids, x = vectors[0][:40], vectors[1][:40]
    found = fit.evolve_rows(x, ids * 64, Search(curve=curve, bits=bits, keep_best=True, fallback_uniform=True))
    assert (found["gain"] >= 1).all()
    a, b = (v.ravel() for v in np.meshgrid(*map(np.array, grid_axes(curve, 25)), indexing="ij"))
    best = fit.grid_losses(curve, x, bits, a, b)[0].max(axis=1)
    assert found["gain"].mean() >= 0.9 * best.mean()


def test_rows_don_t_depend_on_each_other(vectors):
    ids, x = vectors[0][:30], vectors[1][:30]
    whole = fit.evolve_rows(x, ids * 64, Search())
    order = np.random.default_rng(0).permutation(30)
    mixed = fit.evolve_rows(x[order], ids[order] * 64, Search())
    for name in ("p0", "p1", "gain", "iters"):
        assert np.array_equal(whole[name][order], mixed[name])


def test_partitions_give_the_same_fits(spark):
    base = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").where("vec_id < 40")
    rows = [sorted(map(tuple, fit.evolve(base.repartition(n), Search(fixed_iter=6, m=2)).collect())) for n in (1, 5)]
    assert rows[0] == rows[1] and len(rows[0]) == 80
    plan = fit.evolve(base, Search())._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "ReadSchema: struct<vec_id:bigint,embedding:array<float>>" in plan


def test_degenerate_rows():
    x = np.array([[0.5] * 8, [0.0] * 8, [0, 1, 0, 1, 0, 1, 0, 1], [0, 0, 0, 0, 0, 0, 0, 9.0]], dtype=float)
    for curve in curves.NAMES:
        r = fit.evolve_rows(x, np.arange(4), Search(curve=curve, keep_best=True, fallback_uniform=True))
        assert r["degenerate"].tolist() == [True, True, False, False]
        assert r["gain"][:2].tolist() == [1.0, 1.0] and np.isfinite(r["gain"]).all()


def test_values_on_the_uniform_grid_have_gain_one():
    x = np.arange(16, dtype=float)[None, :]
    assert fit.evolve_rows(x, np.zeros(1, np.int64), Search(curve="unif" if False else "kuma", bits=4, fallback_uniform=True))["gain"][0] >= 1


def test_clip_weights_trace_and_seeds(vectors):
    ids, x = vectors[0][:5], vectors[1][:5]
    seen = []
    fit.evolve_rows(x, ids, Search(fixed_iter=7), trace=lambda at, t, mu, g: seen.append((t, len(at))))
    assert seen == [(t, 5) for t in range(1, 8)]
    a = fit.evolve_rows(x, ids, Search(seed=1, fixed_iter=5))["p0"]
    assert not np.array_equal(a, fit.evolve_rows(x, ids, Search(seed=2, fixed_iter=5))["p0"])
    assert np.isfinite(fit.evolve_rows(x, ids, Search(clip_quantile=0.05))["gain"]).all()
    assert np.isfinite(fit.evolve_rows(x, ids, Search(), weights=np.ones_like(x))["gain"]).all()


@pytest.mark.parametrize("bits", [8, 4])
@pytest.mark.parametrize("m", [1, 2, 4])
def test_codec_round_trip(spark, bits, m):
    base = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").where("vec_id < 25").select("vec_id", "embedding")
    mean = prep.fit_mean(base)
    s = Search(curve="pwl", bits=bits, m=m, fixed_iter=5, keep_best=True, fallback_uniform=True)
    coded = codec.encode(base, s, mean)
    back = {r.vec_id: np.array(r.embedding) for r in codec.decode(coded, s, 64, mean).collect()}
    for r in base.collect():
        assert np.abs(back[r.vec_id] - np.array(r.embedding)).max() < (0.02 if bits == 8 else 0.2)
    row = coded.first()
    assert len(row.codes) == 64 * bits // 8 and len(row.params) == m


def test_packing_of_codes():
    codes = np.random.default_rng(0).integers(0, 16, (5, 7))
    assert np.array_equal(codec.unpack(codec.pack(codes, 4), 4, 7), codes)
    wide = np.random.default_rng(0).integers(0, 256, (5, 7))
    assert np.array_equal(codec.unpack(codec.pack(wide, 8), 8, 7), wide)


def test_splits():
    x = np.arange(24.0).reshape(3, 8)
    for split in ("random", "contiguous"):
        perm = prep.make_permutation(8, 4, 3, split)
        assert np.array_equal(prep.unsplit_rows(prep.split_rows(x, 4, perm), 4, perm), x)
    with pytest.raises(ValueError):
        prep.make_permutation(9, 2)


def test_validation(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, []), (4, [1.0]), (5, [float("nan"), 1.0]), (6, [float("inf"), 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    good, bad = prep.validate_vectors(df, 2)
    assert [r.vec_id for r in good.collect()] == [1]
    assert {r.vec_id: r.reason for r in bad.collect()} == {2: "null", 3: "empty", 4: "length", 5: "not finite", 6: "not finite"}
    assert prep.fit_mean(df) == [1.0, 2.0]
    empty = df.where("vec_id > 100")
    assert prep.fit_mean(empty) == [] and fit.evolve(empty, Search()).count() == 0


def test_best_curve_and_mixed_bits(spark):
    base = spark.read.parquet(f"{MIDDLE}/embeddings.parquet").where("vec_id < 12").select("vec_id", "embedding")
    assert fit.best_curve(base, Search(fixed_iter=5)).count() == 12
    rows = codec.encode_mixed(base, Search(fixed_iter=3), [8, 4]).groupBy("bits").agg(F.avg("loss").alias("l")).collect()
    losses = {r.bits: r.l for r in rows}
    assert losses[8] < losses[4]
    assert replace(Search(), m=3).m == 3


def test_length_and_mean_take_all_rows(spark):
    odd = spark.range(1500).selectExpr("array(9.0F) embedding").coalesce(1)
    rows = odd.unionByName(spark.range(2000).selectExpr("array(1.0F, 3.0F) embedding"))
    assert prep.vector_length(rows) == 2 and prep.fit_mean(rows) == [1.0, 3.0]


def test_wide_logistic_rows_are_measured_in_held_memory(monkeypatch):
    x = np.random.default_rng(3).standard_normal((6, 192))
    was = fit.evolve_rows(x, np.arange(6), Search())
    calls, plain = [], curves.loss
    monkeypatch.setattr(curves, "loss", lambda *a: calls.append(a[0]) or plain(*a))
    made = fit.evolve_rows(x, np.arange(6), Search())
    assert calls == ["unif", "logi"]  # what the search starts from and what it returns, no iteration
    monkeypatch.setattr(fit, "_BY_VALUES", 1_000)
    by_loss = fit.evolve_rows(x, np.arange(6), Search())
    assert len(calls) > 10
    for other in (was, by_loss):
        assert np.allclose(made["gain"], other["gain"], rtol=1e-6) and np.array_equal(made["iters"], other["iters"])
