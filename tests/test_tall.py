"""Sets of any number of rows: the same samples, sums and workload results as from rows that are held at once."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from delprop.functions import manyhash
from delprop.functions.hashing import uniform_of
from delprop.functions.sliding import fast_length
from delprop.operators import capture, replay, schedule, spectral, train
from delprop.operators.capture import piece_sums
from delprop.plans import mapped, workloads
from delprop.scratch import stored
from delprop.sources import features as fx
from delprop.sources import tables, tall
from delprop.sources.tables import table
from delprop.spec import ModelSpec


def read(frame, own):
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for ids, valid, take in own.pieces(batch):
                x, y = take(np.arange(len(ids)))
                yield pa.record_batch([pa.array(ids), pa.array(list(x), pa.list_(pa.float64())), pa.array(y), pa.array(valid)], ["sample_id", "features", "label", "is_valid"])

    return {r.sample_id: r for r in frame.mapInArrow(run, "sample_id bigint, features array<double>, label double, is_valid boolean").collect()}


@pytest.mark.parametrize("name", ["sgemm_original", "sgemm_extended", "covtype_small", "higgs"])
def test_narrow_sets_give_the_samples(spark, sf, name):
    w = workloads.scaled(name, 0.1, width=30 if name == "sgemm_extended" else None)
    held = tall.tall(spark, sf, name.split("_")[0], w.kind, w.m, w.q, w.extra)
    got, want = read(held.frame, held.bare()), workloads.samples(spark, sf, name, w).collect()
    assert len(got) == len(want) and held.count() == sum(not r.is_valid for r in want)
    for r in want:
        assert np.array_equal(got[r.sample_id].features, r.features) and got[r.sample_id].is_valid == r.is_valid
        assert got[r.sample_id].label == pytest.approx(r.label, abs=1e-12)


def test_stretches_give_the_frames(spark):
    events = spark.range(3000).select(F.col("id").alias("event_id"), (F.lit("2024-01-01").cast("timestamp") + F.make_interval(mins=F.floor(F.col("id") / 2).cast("int"))).alias("ts"), (F.col("id") % 97 * 1.0).alias("value"))
    want = {r.sample_id: r.features for r in fx.frames(events, 20).collect()}
    got = {}
    for r in fx.stretches(events, 20, 64).collect():
        assert len(r.ids) <= min(64, len(r.vals) - 19)
        got |= {i: r.vals[k : k + 20] for k, i in enumerate(r.ids)}
    assert got == want and len(want) == 3000 - 19 * 2


def test_symmetric_products_are_the_tangents_sums():
    draw = np.random.default_rng(1)
    spec, x, y = ModelSpec("softmax", 5, q=4), draw.normal(size=(200, 5)), draw.integers(0, 4, 200).astype(float)
    w = draw.normal(size=20)
    from delprop.functions.linearize import softmax_pieces

    slopes, offset = softmax_pieces(x @ w.reshape(4, 5).T)
    want = -np.einsum("nij,nk,nl->ikjl", slopes, x, x).reshape(20, 20)
    c, d = piece_sums(x, y, w, spec, {})
    rest = np.eye(4)[y.astype(int)] - offset
    assert np.allclose(c, want) and np.allclose(d, (rest.T @ x).ravel())
    model = spectral.LogisticSpectral(capture.Capture(spec, 200, trajectory=w[None]), spectral.Eigen(np.linalg.qr(draw.normal(size=(20, 20)))[0], np.zeros(20), np.zeros(20), 200), 0)
    few = spectral.frozen_share(x, y, model.eigen.q, w, spec, {})
    assert np.allclose(spectral.frozen_sums(lambda: iter([(x[:90], y[:90]), (x[90:], y[90:])]), 200, model), np.concatenate(few))


@pytest.mark.parametrize("name,scale", [("sgemm_original", {"tau_scale": 0.01}), ("higgs", {"tau_scale": 0.001}), ("covtype_small", {"tau_scale": 0.001}), ("covtype_extended", {"tau_scale": 0.00025, "copies": 2})])
def test_workload_equals_one_held_in_memory(spark, sf, name, scale):
    """Distances to retraining against the operators on whole DataFrames, at two rates from one pass."""
    w, rates = workloads.scaled(name, **scale), (0.1, 0.01)
    got = {(r.rate, r.method): r for r in workloads.run(spark, sf, name, rates, ("replay", "spectral", "stale"), repeat=1, workload=w).collect()}
    clean = stored(workloads.samples(spark, sf, name, w), "test-workload")
    for rate in rates:
        rows, spec = clean.where("not is_valid"), workloads.spec_of(w)
        rows = rows if w.dirty is None else fx.dirty(rows, rate, "rescale", w.dirty).drop("dirty")
        rows = stored(rows, "test-dirty")
        gone, n = fx.removals_at(rows, rate), rows.count()
        old, truth = train.train(rows, spec, keep_trajectory=True), train.retrain(rows, gone, spec, n).w
        assert got[rate, "retrain"].n == n and got[rate, "retrain"].removed == gone.count()
        assert got[rate, "stale"].distance == pytest.approx(np.linalg.norm(old.w - truth), rel=1e-6)
        if w.kind == "linear":
            w_new = spectral.spectral_linear(spectral.fit_eigen(rows, spec), rows, gone, spec)
        else:
            at = spectral.switch_point(spec)
            held = capture.capture_logistic(rows, old.trajectory, spec, n, upto=at)
            w_new = spectral.spectral_logistic(spectral.fit_logistic(rows, held, at), rows, gone)
        # factors of logistic models keep eigenvalues above a hundredth of the largest
        assert got[rate, "spectral"].distance == pytest.approx(np.linalg.norm(w_new - truth), rel=1e-6 if spec.size <= 128 else 0.05)


def test_rows_stay_in_mapped_files(spark, sf):
    """What an update works on is not held in this process: parts are views of files, and few at a time."""
    w = workloads.scaled("sgemm_original", 0.01)
    spec = workloads.spec_of(w)
    held = tall.tall(spark, sf, "sgemm", w.kind, w.m)
    n = held.count()
    local = mapped.Mapped(mapped.pick(held, spec, n, [0.01, 0.2]), spec.m, 2)
    left, _ = local.split(1)
    assert isinstance(local.x, np.memmap) and all(np.shares_memory(x, local.x) for x, _ in left.values() if len(x))
    assert local.removed_count(1) > local.removed_count(0) > 0
    assert all(x.nbytes <= mapped.PART_BYTES for x, _ in local.removed(1))
    assert sum(len(y) for _, y in local.removed(1)) == fx.removals_at(workloads.samples(spark, sf, "sgemm_original", w).where("not is_valid"), 0.2).count()
    local.close()


@pytest.mark.parametrize("rows", [tables.BROADCAST_ROWS, 0])
def test_lines_are_dealt_out_once(spark, sf, monkeypatch, rows):
    """The stored set's joins shuffle lines by order only; with more parts and suppliers than may be sent, by their keys as well.  The rows are those of the plain star."""
    monkeypatch.setattr(tables, "BROADCAST_ROWS", rows)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = tables.lean_star(spark, sf).select(fx.line_id().alias("sample_id"), *fx.fifty_four_columns())
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning(") == (4 if rows else 8)
        want = tables.star(spark, sf).select(fx.line_id().alias("sample_id"), *fx.fifty_four_columns())
        assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_parts_are_sent_without_strings(spark, sf, monkeypatch):
    """Brands and types come to the lines as codes, also those of no known name."""
    plans, kept = [], tall.stored
    monkeypatch.setattr(tall, "stored", lambda df, *a, **o: (plans.append(df._jdf.queryExecution().optimizedPlan().toString()), kept(df, *a, **o))[1])
    tall.tall(spark, sf, "covtype", "softmax", 54, 7)
    lines = [line for line in plans[0].splitlines() if "Project [" in line and "p_type" in line]
    assert lines and all("AS type_no" in line and "AS brand_no" in line for line in lines)
    rows = spark.createDataFrame([("Brand#7", "PROMO X"), ("Brand#25", "SMALL"), ("Brand#1", "other"), (None, None)], "p_brand string, p_type string").withColumns(fx.part_codes())
    names = [f"c{i}" for i in range(31)]
    plain, coded = (rows.select(*[c.alias(n) for c, n in zip(columns[10:41], names, strict=True)]).collect() for columns in (fx.fifty_four_columns(), fx.fifty_four_columns(coded=True)))
    assert plain == coded and sum(map(sum, plain)) == 5


def test_stored_sets_use_the_lean_star(spark, sf, monkeypatch):
    monkeypatch.setattr(tall, "lean_star", lambda *a: (_ for _ in ()).throw(KeyError("lean")), raising=True)
    with pytest.raises(KeyError, match="lean"):
        tall.tall(spark, sf, "sgemm", "linear", 18)


def test_shuffle_files_and_heap_are_given_back(spark, sf, monkeypatch):
    """After the set is stored, while rows arrive, when they have, and after each rate."""
    calls, kept = [], mapped.settled
    for module in (tall, mapped, workloads):
        monkeypatch.setattr(module, "settled", lambda s, at=module.__name__: (calls.append(at.split(".")[-1]), kept(s)))
    monkeypatch.setattr(mapped, "SETTLE_BYTES", 1000)
    rows = workloads.run(spark, sf, "sgemm_original", (0.1, 0.2), ("replay", "stale"), repeat=1, workload=workloads.scaled("sgemm_original", 0.01)).collect()
    assert len(rows) == 6 and calls[0] == "tall" and calls.count("mapped") > 1 and calls[-2:] == ["workloads"] * 2


def test_sets_are_stored_in_chunks(spark, sf):
    """Spark moves a row for thousands of samples, and what is squeezed comes back bit by bit."""
    held = tall.tall(spark, sf, "covtype", "softmax", 54, 7)
    n = table(spark, sf, "lineitem").count()
    rows = held.frame.collect()
    assert len(rows) <= 12 and sum(len(r.body) for r in rows) < 80 * n
    draw = np.random.default_rng(3)
    for values in (draw.integers(0, 2, 3000) * 1.0, draw.integers(0, 50, 3000) / 7, draw.normal(size=3000), np.array([0.0, -0.0, 1.0, np.nan]), np.array([-1.0, 1.0])):
        own = draw.permutation(len(values))[: len(values) // 2]
        assert tall._plain(tall.squeezed(values), own).astype(float).tobytes() == values[own].tobytes()
    assert [tall.squeezed(v).nbytes for v in (np.ones(4096), np.arange(4096) % 50 / 7)] == [512, 4096 + 50 * 8]


def test_picked_rows_are_packed_once(spark, sf, monkeypatch):
    """What comes to the driver is read from the table that the pass over all rows wrote; no other is made."""
    labels, kept = [], mapped.stored
    monkeypatch.setattr(mapped, "stored", lambda df, label, **b: (labels.append(label), kept(df, label, **b))[1])
    w = workloads.scaled("covtype_small", 0.001)
    spec, held = workloads.spec_of(w), tall.tall(spark, sf, "covtype", w.kind, w.m, w.q)
    n = held.count()
    picked = mapped.pick(held, spec, n, [0.1])
    local = mapped.Mapped(picked, spec.m, 1)
    assert labels == ["picked"] and dict(picked.dtypes)["d"] == "binary"
    assert local.removed_count(0) > 0 and len(local.y) > 0
    local.close()


@pytest.mark.parametrize("factor", [1.0, 10.0])
def test_touched_rows_are_those_in_memory(spark, sf, factor):
    """Rows that some iteration touches, from the packed table and from the samples; removed ones with their error."""
    w = workloads.scaled("covtype_large_1", 0.02, batch=400)
    spec, held = workloads.spec_of(w), tall.tall(spark, sf, "covtype", w.kind, w.m, w.q)
    n = held.count()
    got = {r.sample_id: r for r in mapped.touched(mapped.pick(held, spec, n, [0.1, 0.3]), spec.m, 0, factor).collect()}
    rows = workloads.samples(spark, sf, "covtype_large_1", w).where("not is_valid")
    want = {r.sample_id: r for r in schedule.assign(fx.dirty(rows, 0.1, "rescale", factor), spec, n).collect()}
    assert set(got) == set(want) and any(r.dirty for r in want.values())
    assert all(got[i].block_id == r.block_id and got[i].label == r.label and np.allclose(got[i].features, r.features, rtol=1e-15) for i, r in want.items())


@pytest.mark.parametrize("kind,tau", [("softmax", 3), ("softmax", 9), ("linear", 3)])
def test_batches_are_factored_in_one_task_each(spark, sf, kind, tau):
    """The sums of :func:`capture.capture_factors`, without partial factors that meet in rounds; iterations may come back to a batch."""
    spec = ModelSpec(kind, 4, q=3 if kind == "softmax" else 1, eta=0.05, tau=tau, batch_size=1000, schedule="cyclic")
    rows = stored(fx.small(spark, sf, 3, kind, 3), "test-batches")
    n = rows.count()
    path = train.train(rows, spec, n, keep_trajectory=True).trajectory
    own = capture.capture_batches(rows, spec, n, path, eps=1e-12)
    plan = own.factors._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and plan.count("FlatMapGroupsInArrow") == 1
    got, want = (replay.load_sums(c) for c in (own, capture.capture_factors(rows, spec, n, path, eps=1e-12)))
    w = np.random.default_rng(2).normal(size=spec.size)
    assert set(got) == set(want) and len(got) == min(tau, spec.blocks(n) if kind == "linear" else tau)
    for t, (count, apply, cross) in want.items():
        assert got[t][0] == count and np.allclose(got[t][2], cross) and np.allclose(got[t][1](w), apply(w))


def test_few_files_are_dealt_to_all_cores(spark):
    """Wide sums of a set in one file do not run in one task."""
    seen = tall.Tall(stored(spark.range(64).select(F.array("id").alias("ids"), F.array(F.lit(0.0)).alias("vals"), F.array(F.lit(0.0)).alias("labels"), F.array(F.lit(False)).alias("valid")).coalesce(1), "test-few"), "windows", "linear", 1)

    def partial(ids, valid, take):
        from pyspark import TaskContext

        yield TaskContext.get().partitionId(), len(ids), np.zeros(60_000)

    got = seen.sums(partial, 60_000).select("block_id", "cnt").collect()
    assert len(got) > 1 and sum(r.cnt for r in got) == 64


def test_places_and_teachers_are_made_once():
    """A stretch of 1,024 windows is less work than the places of a packed triangle of order 1,316, or than 1,316 hashed weights."""
    from delprop.functions import vector

    assert vector._upper(1316) is vector._upper(1316) and tall.teachers(188, 7) is tall.teachers(188, 7)
    assert np.array_equal(tall.teachers(5, 3), np.array([fx.teacher(5, c) for c in range(3)]).T)
    a = np.random.default_rng(4).normal(size=(6, 6))
    a = np.asfortranarray(a + a.T)
    assert np.array_equal(vector.pack(a), a[np.triu_indices(6)]) and np.array_equal(vector.unpack(vector.pack(a), 6), a)


def test_the_joins_shuffle_files_go_with_the_set_stored(spark, sf):
    """They are as large as the set, and what follows needs the disk."""
    import time

    def files():
        found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {found.apply(i).getName() for i in range(found.size()) if found.apply(i).getName().startswith("shuffle_")}

    before = files()
    held = tall.tall(spark, sf, "sgemm", "linear", 48, extra=30)
    for _ in range(20):
        if not files() - before:
            break
        time.sleep(0.5)
    assert not files() - before and held.count() > 0


def test_garbage_is_collected_twice(spark, monkeypatch):
    """At size, shuffle files outlived a single collection until the next one, after the touched rows had come."""
    from delprop import scratch

    calls, kept = [], scratch.gc.collect
    monkeypatch.setattr(scratch.gc, "collect", lambda: (calls.append(1), kept())[1])
    scratch.settled(spark)
    assert len(calls) == 2


def test_window_sums_equal_the_sums_of_rows():
    """Stretches of unlike lengths, one without a row that counts."""
    draw = np.random.default_rng(2)
    spec, w = ModelSpec("softmax", 11, q=4), draw.normal(size=44) / 3
    stretches = [(draw.normal(size=k + 10), draw.integers(0, 4, k).astype(float), draw.random(k) < share) for k, share in ((60, 0.9), (1, 1.0), (37, 0.5), (20, 0.0))]
    rows = [(np.lib.stride_tricks.sliding_window_view(v, 11)[own], y[own]) for v, y, own in stretches]
    c, d = piece_sums(np.concatenate([x for x, _ in rows]), np.concatenate([y for _, y in rows]), w, spec, {})
    n, got_c, got_d = capture.window_sums(stretches, w, spec)
    assert n == sum(len(y) for _, y in rows) and np.allclose(got_c, c, rtol=0, atol=1e-12) and np.allclose(got_d, d, rtol=0, atol=1e-12)
    assert all(fast_length(k) == next(n for n in range(k, 4 * k) if n in _smooth()) for k in range(1, 300))


def _smooth():
    return {2**a * 3**b * 5**c for a in range(11) for b in range(7) for c in range(5)}


def test_the_tail_of_windows_is_that_of_their_rows(spark, tmp_path):
    events = spark.range(1500).select(F.col("id").alias("event_id"), (F.lit("2024-01-01").cast("timestamp") + F.make_interval(secs=F.col("id"))).alias("ts"), (F.col("id") * 37 % 97 * 1.0).alias("value"))
    events.write.parquet(f"{tmp_path}/events.parquet")
    w = workloads.scaled("heartbeat_extended", 0.00025, copies=2)
    spec = workloads.spec_of(w)
    held = tall.tall(spark, str(tmp_path), "heartbeat", w.kind, w.m, w.q, 0, w.copies)
    at = np.random.default_rng(3).normal(size=spec.size) / 50
    got, want = workloads._tail(held, at, spec).first(), workloads._weighted(held, spec, lambda x, y: piece_sums(x, y, at, spec, {}), None).first()
    assert got.cnt == want.cnt == held.count() > 2000
    assert np.allclose(got.gram, want.gram, rtol=0, atol=1e-9) and np.allclose(got.cross, want.cross, rtol=0, atol=1e-9)


def test_ids_of_all_lengths_are_hashed_at_once(monkeypatch):
    ids, calls = np.r_[0, 10 ** np.arange(19), 10 ** np.arange(1, 19) - 1, 2**63 - 1], []
    first = manyhash._first_word
    monkeypatch.setattr(manyhash, "_first_word", lambda words, n: calls.append(n) or first(words, n))
    assert manyhash.uniforms(ids, ["rm", "gumbel0"]).tolist() == [[uniform_of(int(i), s) for s in ("rm", "gumbel0")] for i in ids]
    assert calls == [2 * len(ids)] and manyhash.uniforms(ids[:0], ["rm"]).shape == (0, 1)


@pytest.mark.parametrize("name", ["covtype_large_1", "covtype_small", "covtype_large_2", "sgemm_extended", "heartbeat", "heartbeat_extended", "covtype_extended"])
def test_registered_workloads_are_the_published_ones(monkeypatch, name):
    """No fewer iterations, columns, copies or rows a batch."""
    from delprop.plans import queries

    ran = []
    monkeypatch.setattr(workloads, "run", lambda spark, folder, called, **how: ran.append((called, how["workload"])))
    queries.QUERIES[f"workload_{name}"](None, "")
    assert ran == [(name, workloads.WORKLOADS[name])]


@pytest.mark.parametrize("name,scale", [("covtype_large_1", {"tau_scale": 0.06, "batch": 300}), ("sgemm_extended", {"tau_scale": 0.015, "width": 218})])
def test_windows_of_iterations_give_the_run_that_holds_all(spark, sf, monkeypatch, name, scale):
    """Factors are made, replayed and deleted some iterations at a time, over several passes of the batches; influence serves any number of columns."""
    w = workloads.scaled(name, **scale)
    w = w if w.kind == "softmax" else replace(w, batch=300)
    held, kept = [], replay.load_sums
    monkeypatch.setattr(replay, "load_sums", lambda c, *a: (held.append(kept(c, *a)), held[-1])[1])

    def results(size):
        monkeypatch.setattr(workloads, "WINDOW_BYTES", size)
        held.clear()
        rows = workloads.run(spark, sf, name, (0.1,), repeat=2, workload=w).collect()
        return {r.method: r for r in rows}, len(held), max(workloads._array_bytes(s) for s in held)

    kept_stored, written = workloads.stored, []
    monkeypatch.setattr(workloads, "stored", lambda df, label, **o: (written.append((label, o)), kept_stored(df, label, **o))[1])
    monkeypatch.setattr(workloads.measures, "stored", lambda *a: pytest.fail("a frame is stored twice"), raising=False)
    (whole, once, most), (got, many, least) = results(1 << 40), results(400_000)
    assert {label for label, _ in written} == {"blocks", "factors"} and all(o["parquet.page.size.row.check.min"] == "1" for _, o in written)
    assert once == 1 and many > 3 and least < most / 2
    assert set(got) == set(whole) >= {"retrain", "spectral", "influence", "stale"}
    for method, r in whole.items():
        assert got[method].distance == pytest.approx(r.distance, rel=1e-6, abs=1e-9) and got[method].bytes == r.bytes


def test_few_rows_and_bound_classes_are_factored_small():
    """The eigenpairs of the whole C, from a matrix of the batch's rows or without the direction that all classes share."""
    draw = np.random.default_rng(5)
    for spec, x in ((ModelSpec("linear", 40), draw.normal(size=(15, 40))), (ModelSpec("softmax", 6, q=4), draw.normal(size=(50, 6)))):
        y, w = draw.integers(0, 4, len(x)).astype(float), draw.normal(size=spec.size)
        c = x.T @ x if spec.kind == "linear" else piece_sums(x, y, w, spec, {})[0]
        r = capture._eigen_record(3, x, y, w, spec, 0.01, "residual", {}).to_pylist()[0]
        p, v = capture.factor(c, 0.01, "residual")
        got = np.frombuffer(r["v"]).reshape(spec.size, r["r"])
        assert r["r"] == p.shape[1] and np.allclose((got * np.frombuffer(r["values"])) @ got.T, p @ v.T, atol=1e-10)
