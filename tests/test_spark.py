"""The Spark layer: provenance algebra, engines, captures, removal sets, sinks, streams, and queries against their SQL."""

import math
import os
import re

from dataclasses import replace

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from delprop.functions.vector import unpack
from delprop.operators import capture, prov, replay, sparse, spectral, train
from delprop.plans import maintain, queries, workloads
from delprop.scratch import stored
from delprop.sources import features as fx
from delprop.sources import tables
from delprop.spec import ModelSpec


def canonical(frame):
    columns = sorted(frame.columns)
    rows = []
    for r in frame[columns].itertuples(index=False):
        rows.append(tuple(None if x is None or x != x else round(float(x), 9) if isinstance(x, float) else str(x) for x in r))
    return columns, sorted(rows, key=str)


@pytest.mark.parametrize("name", ["hash_uniform", "features_28", "gram_cube", "train_reshuffle_linear", "replay_linear", "replay_linear_composed", "replay_binary", "spectral_linear", "influence_multi", "poly_mul", "compare_models", "replay_softmax", "replay_sparse", "spectral_binary", "spectral_linear_many", "replay_linear_truncated", "update_chosen", "method_costs", "train_rates_linear"])
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for file in os.listdir(sf):
        con.execute(f"CREATE VIEW {file.split('.')[0]} AS SELECT * FROM read_parquet('{sf}/{file}')")
    assert canonical(entry.queries()[name](spark, sf).toPandas()) == canonical(con.execute(entry.oracle_sql()[name]).df())


def test_registry_is_consistent():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def terms(spark, rows):
    return spark.createDataFrame(rows, prov.TERMS)


def values(frame):
    return {r.pos: r.value for r in prov.evaluate(frame).collect()}


def test_three_term_example(spark):
    """Terms over two tokens each; deleting the third token leaves the first and the last vector."""
    frame = terms(spark, [({"p": 2, "q": 1}, 2, 1, [1.0, 0.0]), ({"q": 1, "r": 3}, 2, 1, [0.0, 1.0]), ({"p": 1, "s": 1}, 2, 1, [2.0, 3.0])])
    assert values(prov.delete(frame, ["r"])) == {0: 3.0, 1: 3.0}
    assert values(frame) == {0: 3.0, 1: 4.0}
    assert values(prov.delete(frame, [])) == values(frame)


def test_two_row_decomposition(spark):
    rows = spark.createDataFrame([(1, [1.0, 2.0], 0.0), (2, [3.0, 4.0], 0.0)], "sample_id bigint, features array<double>, label double")
    assert values(prov.delete(prov.decompose(rows), ["p1"])) == {0: 3.0, 1: 4.0}
    labels = {r[0] for r in prov.gram(prov.decompose(rows)).select(prov.label(F.col("monomial"))).collect()}
    assert labels == {"p1^2", "p2^2"}


def text(frame):
    return {r.m: r.coefficient for r in frame.select(prov.label(F.col("monomial")).alias("m"), "coefficient").collect()}


def test_semiring_laws(spark):
    a, b, c = (spark.createDataFrame(rows, prov.POLYNOMIAL) for rows in ([({"p": 1}, 2), ({"q": 2}, 1)], [({"p": 1}, 3), ({}, 1)], [({"r": 1}, 5)]))
    assert text(prov.add(a, b)) == text(prov.add(b, a)) and text(prov.mul(a, b)) == text(prov.mul(b, a))
    assert text(prov.mul(a, prov.one(spark))) == text(a) and text(prov.mul(a, prov.zero(spark))) == {} and text(prov.add(a, prov.zero(spark))) == text(a)
    assert text(prov.mul(prov.mul(a, b), c)) == text(prov.mul(a, prov.mul(b, c)))
    assert text(prov.mul(a, prov.add(b, c))) == text(prov.add(prov.mul(a, b), prov.mul(a, c)))
    assert text(prov.idempotent(prov.mul(a, a))) == {"p": 4, "p*q": 4, "q": 1}


def test_products_of_annotated_matrices(spark):
    draw = np.random.default_rng(0)
    x, y = draw.normal(size=(2, 3)), draw.normal(size=(3, 2))
    got = prov.matmul(prov.annotate(x, {"p": 1}, spark), prov.annotate(y, {"q": 1}, spark)).collect()
    assert len(got) == 1 and got[0].monomial == {"p": 1, "q": 1} and np.allclose(got[0].cells, (x @ y).ravel())
    scaled = prov.scale(spark.createDataFrame([({"r": 1}, 3)], prov.POLYNOMIAL), prov.annotate(x, {"p": 1}, spark)).first()
    assert np.allclose(scaled.cells, 3 * x.ravel())


def small_set(spark, n=3):
    draw = np.random.default_rng(5)
    return spark.createDataFrame([(i, [float(v) for v in draw.normal(size=2)], float(draw.choice([-1.0, 1.0]))) for i in range(n)], "sample_id bigint, features array<double>, label double")


def test_symbolic_iteration_equals_retraining_for_every_removal(spark):
    rows = small_set(spark)
    data = rows.collect()
    x, y = np.array([r.features for r in data]), np.array([r.label for r in data])
    for mask in range(7):
        keep = np.array([not mask >> i & 1 for i in range(3)])
        spec = ModelSpec("linear", 2, lam=0.1, eta=0.2, tau=2)
        got = prov.iterate_linear(rows, spec, divisor=int(keep.sum()))
        w = values(prov.delete(got, [f"p{i}" for i in range(3) if not keep[i]]))
        assert np.allclose([w[0], w[1]], train.descend({0: (x[keep], y[keep])}, spec, 1)[0])
        if mask in (0, 4):
            spec = ModelSpec("binary", 2, lam=0.1, eta=0.2, tau=2)
            _, path = train.descend({0: (x, y)}, spec, 1, keep=True)
            got = prov.iterate_logistic(rows, spec, path, divisor=int(keep.sum()))
            w = values(prov.delete(got, [f"p{i}" for i in range(3) if not keep[i]]))
            assert np.allclose([w[0], w[1]], replay.replay_survivors({0: (x[keep], y[keep])}, path, spec, 1))
    with pytest.raises(ValueError):
        prov.iterate_linear(rows, ModelSpec("linear", 2, eta=0.1, tau=1000))


def test_terms_diverge_unless_products_are_idempotent():
    """One sample, one feature: sizes of the terms of (1 - eta lam + c p)^t."""
    s, c = 1 - 0.3 * 0.1, 0.6
    for t, large, small in ((10, 2.27e1, 0.737), (40, 8.83e6, 0.296), (160, 1.43e30, 0.00765)):
        sizes = [math.comb(t, k) * s ** (t - k) * c**k for k in range(t + 1)]
        assert max(sizes) == pytest.approx(large, rel=0.02)
        assert s**t == pytest.approx(small, rel=0.02)


def test_engines_agree(spark, sf):
    rows, spec = fx.small(spark, sf, 2, "softmax", 3), ModelSpec("softmax", 3, q=3, lam=0.1, eta=0.1, tau=3, batch_size=2000, schedule="cyclic")
    local, jobs = train.train(rows, spec, engine="local"), train.train(rows, spec, engine="jobs", keep_trajectory=True)
    assert np.allclose(local.w, jobs.w) and jobs.trajectory.shape == (4, 9)
    with pytest.raises(MemoryError):
        train.train(rows, spec, engine="local", local_bytes=10)


def test_stored_capture_round_trip(spark, sf, tmp_path):
    rows = fx.small(spark, sf, 2, "binary")
    spec = ModelSpec("binary", 3, lam=0.1, eta=0.2, tau=4, batch_size=3000, schedule="cyclic")
    fit = train.train(rows, spec, keep_trajectory=True)
    held = capture.capture_logistic(rows, fit.trajectory, spec, fit.n)
    tables.write_capture(held, str(tmp_path / "c"))
    again = tables.read_capture(spark, str(tmp_path / "c"))
    gone = fx.removals_at(rows, 0.05)
    assert again.spec == spec and np.allclose(replay.replay(again, rows, gone), replay.replay(held, rows, gone))


def test_factors_from_rows_for_softmax(spark, sf):
    rows, spec = fx.small(spark, sf, 2, "softmax", 3), ModelSpec("softmax", 3, q=3, lam=0.1, eta=0.1, tau=4, batch_size=3000, schedule="cyclic")
    fit = train.train(rows, spec, keep_trajectory=True)
    gone = fx.removals_at(rows, 0.05)
    a = replay.replay(capture.capture_logistic(rows, fit.trajectory, spec, fit.n), rows, gone)
    b = replay.replay(capture.capture_factors(rows, spec, fit.n, fit.trajectory, eps=1e-12), rows, gone)
    assert np.allclose(a, b, atol=1e-8)


def test_single_sample_schedule_replays(spark, sf):
    rows, spec = fx.small(spark, sf), ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=30, schedule="single")
    gone = fx.removals_at(rows, 0.2)
    assert np.allclose(replay.replay(capture.capture_linear(rows, spec), rows, gone), train.retrain(rows, gone, spec).w, atol=1e-9)


def test_spectral_many_equals_one_by_one(spark, sf):
    rows, spec = fx.small(spark, sf), ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=30)
    sets = fx.ten_removals(rows, 0.01, 2)
    eigen = spectral.fit_eigen(rows, spec)
    many = spectral.spectral_many(eigen, rows, sets, spec)
    for s in range(2):
        assert np.allclose(many[s], spectral.spectral_linear(eigen, rows, sets.where(F.col("subset_id") == s), spec))


@pytest.mark.parametrize("form", ["csv", "json", "orc", "parquet", "libsvm"])
def test_readers(spark, tmp_path, form):
    path = str(tmp_path / form)
    if form == "libsvm":
        (tmp_path / "s.txt").write_text("1 1:0.5 2:2\n-1 2:1\n")
        rows = tables.read_samples(spark, str(tmp_path / "s.txt"), "libsvm", numFeatures="2")
        assert sorted(map(tuple, (r.features for r in rows.collect()))) == [(0.0, 1.0), (0.5, 2.0)]
        return
    frame = spark.createDataFrame([(1, 0.5, 2.0, 1.0), (2, 0.0, 1.0, -1.0)], "sample_id bigint, a double, b double, label double")
    writer = frame.write.format(form)
    (writer.option("header", True) if form == "csv" else writer).save(path)
    got = tables.read_samples(spark, path, form, features=["a", "b"]).orderBy("sample_id").collect()
    assert [(r.sample_id, list(r.features), r.label) for r in got] == [(1, [0.5, 2.0], 1.0), (2, [0.0, 1.0], -1.0)]


def test_workload_reproduces_the_order_of_methods(spark, sf):
    got = {r.method: r for r in workloads.run(spark, sf, "sgemm_original", rates=(0.1,), repeat=1, workload=workloads.scaled("sgemm_original", 0.3)).collect()}
    assert got["replay"].distance < 1e-8
    assert got["spectral"].distance < got["influence"].distance and got["spectral"].distance < got["stale"].distance
    got = {r.method: r for r in workloads.run(spark, sf, "higgs", rates=(0.1,), repeat=1, workload=replace(workloads.scaled("higgs", 0.01), eta=2e-2)).collect()}
    assert got["replay"].distance < got["stale"].distance and got["replay"].cosine > 0.95


@pytest.fixture(scope="module")
def few(spark, sf):
    """The small fixture and a tenth of it to remove, both read once."""
    rows = fx.small(spark, sf).persist()
    return rows, fx.removals_at(rows, 0.1).persist()


def test_replay_beyond_this_process(spark, few, sf):
    """Aggregated removed rows and streamed sums give the same model as the local way; so do the sets of update_many."""
    rows, gone = few
    spec = ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=12, batch_size=1000, schedule="cyclic")
    held = capture.capture_linear(rows, spec)
    assert np.allclose(replay.replay(held, rows, gone, local_bytes=1), replay.replay(held, rows, gone), atol=1e-10)
    sets = gone.unionByName(spark.createDataFrame([(7, -1)], "subset_id int, sample_id bigint"))
    a, b = ({r.subset_id: r.w for r in replay.update_many(held, rows, sets, local_bytes=x).collect()} for x in (1, 1 << 30))
    assert set(a) == set(b) == {0, 7} and all(np.allclose(a[k], b[k], atol=1e-10) for k in a)
    for kind, q in (("binary", 1), ("softmax", 3)):
        rows = fx.small(spark, sf, 2, kind, q).persist()
        spec = ModelSpec(kind, 3, q=q, lam=0.1, eta=0.1, tau=4, batch_size=3000, schedule="cyclic")
        fit = train.train(rows, spec, keep_trajectory=True)
        held = capture.capture_logistic(rows, fit.trajectory, spec, fit.n)
        assert np.allclose(replay.replay(held, rows, gone, local_bytes=1), replay.replay(held, rows, gone), atol=1e-10)


def test_retraining_a_one_sample_schedule_beyond_this_process(few):
    rows, gone = few
    spec = ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=5, schedule="single")
    near, far = (train.retrain(rows, gone, spec, local_bytes=x).w for x in (1 << 30, 1))
    assert np.allclose(near, far, atol=1e-12) and np.linalg.norm(near) > 0


def test_sparse_models_beyond_this_process(spark, sf):
    rows = fx.hashed_words(spark, sf, 500).persist()
    n, gone = rows.count(), fx.removals_at(rows, 0.2)
    spec = ModelSpec("binary", 500, lam=0.1, eta=0.5, tau=3, batch_size=-(-n // 2), schedule="cyclic")
    near, far = {}, {}
    assert np.allclose(sparse.train(rows, spec, n, near), sparse.train(rows, spec, n, far, local_bytes=1), atol=1e-10)
    assert np.allclose(sparse.replay(rows, gone, spec, n, near), sparse.replay(rows, gone, spec, n, far, local_bytes=1), atol=1e-8)
    assert np.allclose(sparse.retrain(rows, gone, spec, n), sparse.retrain(rows, gone, spec, n, local_bytes=1), atol=1e-10)


def test_spectral_keeps_sets_without_rows_and_takes_many_features(spark, few):
    rows, gone = few
    spec = ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=20)
    eigen = spectral.fit_eigen(rows, spec)
    got = spectral.spectral_many(eigen, rows, gone.unionByName(spark.createDataFrame([(9, -1)], "subset_id int, sample_id bigint")), spec)
    assert set(got) == {0, 9} and np.allclose(got[9], spectral.spectral_linear(eigen, rows, gone.limit(0), spec))
    assert np.allclose(got[0], spectral.spectral_linear(eigen, rows, gone, spec))


def test_factors_of_a_block_meet_in_rounds(few, monkeypatch):
    rows, _ = few
    spec = ModelSpec("linear", 4, lam=0.1, eta=0.05, tau=3)
    whole = capture.capture_linear(rows, spec).blocks.first()
    r = capture.capture_factors(rows.repartition(7), spec, eps=1e-14).factors.first()
    p, v = (np.array(x).reshape(4, r.r) for x in (r.p, r.v))
    assert np.allclose(p @ v.T, unpack(np.array(whole.gram), 4)) and np.allclose(r.cross, whole.cross) and r.cnt == whole.cnt


def test_frames_do_not_depend_on_the_chunks(spark):
    events = spark.range(400).select(F.col("id").alias("event_id"), (F.lit("2024-01-01").cast("timestamp") + F.make_interval(hours=F.floor(F.col("id") / 10).cast("int"))).alias("ts"), (F.col("id") * 1.0).alias("value"))
    few, many = ({r.sample_id: r.features for r in fx.frames(events, 9, chunk).collect()} for chunk in (16, 8192))
    assert few == many and len(few) == 240 - 8 + 160 - 8


def test_library_imports_without_the_optional_subpackage():
    for folder, _, files in os.walk(os.path.join(os.path.dirname(queries.__file__), "..")):
        for f in files:
            if f.endswith(".py") and os.sep + "llm" not in folder:
                with open(os.path.join(folder, f)) as source:
                    assert not re.search(r"delprop\.llm|from \.+llm", source.read())


def test_maintained_models_take_the_planners_method(spark, sf):
    """Binary, softmax and sparse models: the chosen method's result is near retraining; unknown ids change nothing."""
    for kind, q, bound in (("binary", 1, 1e-3), ("softmax", 3, 1e-2)):
        rows = stored(fx.small(spark, sf, 2, kind, q), "test-samples")
        spec = ModelSpec(kind, 3, q, lam=0.1, eta=0.1, tau=20)
        kept, gone = maintain.maintain(rows, spec), fx.removals_at(rows, 0.02)
        got = maintain.update(kept, rows, gone)
        assert got.method == "spectral" and got.removed == gone.count()
        assert np.abs(got.w - train.retrain(rows, gone, spec).w).max() < bound
        none = maintain.update(kept, rows, spark.createDataFrame([(-1,)], "sample_id bigint"))
        assert none.removed == 0 and np.abs(none.w - kept.w).max() < bound
        heavy = fx.removals_at(rows, 0.6)
        assert np.allclose(maintain.update(kept, rows, heavy).w, train.retrain(rows, heavy, spec).w, atol=5e-2)


def test_maintained_sparse_model_replays_its_rows(spark, sf):
    rows = stored(fx.hashed_words(spark, sf), "test-samples")
    spec = ModelSpec("binary", 47236, lam=0.5, eta=0.1, tau=10)
    kept, gone = maintain.maintain(rows, spec), fx.removals_at(rows, 0.05)
    got = maintain.update(kept, rows, gone)
    assert got.method == "replay_sparse" and kept.nonzeros > 0
    assert np.abs(got.w - sparse.retrain(rows, gone, spec, kept.n)).max() < 1e-3


@pytest.mark.parametrize("name", ["interval_schedule", "interp_table"])
def test_query_reads_a_given_table_and_equals_sql(spark, sf, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{sf}/lineitem.parquet')")
    got = entry.queries()[name](spark, sf)
    assert got.agg(F.sum("cnt")).first()[0] >= 6000
    assert canonical(got.toPandas()) == canonical(con.execute(entry.oracle_sql()[name]).df())
