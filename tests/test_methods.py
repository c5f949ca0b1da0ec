"""Hand cases and invariants of the methods."""

import math
import pathlib
import subprocess
import sys
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from manifold_dp import sources
from manifold_dp.operators import align, arrays, baselines, experiments, features, kernel, ledger, metrics, noise, release, retrieval, sensitivity, sweep
from manifold_dp.operators.kernel import DenseOp, FeatureMapOp, SparseOp
from manifold_dp.operators.labels import LabelOp
from manifold_dp.operators.maps import gram, spectral
from manifold_dp.operators.step import contrast_step, majorant, objective, run

SCHEMA = "id long, x array<double>, label int, role string"


def points(spark, xs, labels=None, roles=None, start=0):
    n = len(xs)
    return spark.createDataFrame([(start + i, [float(z) for z in xs[i]], labels[i] if labels else None, roles[i] if roles else None) for i in range(n)], SCHEMA)


def matrix(df, col="v"):
    return np.array([r[col] for r in df.orderBy("id").collect()])


@pytest.fixture(scope="module")
def tri3(spark):
    return points(spark, [(1, 0), (0, 1), (-1, 0)], [0, 0, 1]).cache()


@pytest.fixture(scope="module")
def some(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(40, 6))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    return points(spark, x, [int(i % 4) for i in range(40)]).cache()


def dense(x, sigma):
    w = np.exp(-((x[:, None] - x[None]) ** 2).sum(2) / sigma)
    np.fill_diagonal(w, 0)
    return w


def test_tri3_weights_and_degrees(tri3):
    w = {(r.i, r.j): r.w for r in kernel.pairs(tri3, 1.0).collect()}
    assert w[0, 1] == pytest.approx(math.exp(-2)) and w[0, 2] == pytest.approx(math.exp(-4))
    deg = {r.id: r.deg for r in kernel.degrees(tri3, DenseOp(1.0)).collect()}
    assert deg[0] == pytest.approx(math.exp(-2) + math.exp(-4)) and deg[1] == pytest.approx(2 * math.exp(-2))


def test_tri3_step_by_hand(tri3, spark):
    v = spark.createDataFrame([(0, [1.0]), (1, [0.0]), (2, [0.0])], "id long, v array<double>")
    out = matrix(contrast_step(v, DenseOp(1.0).over(tri3), None, 0.0))[:, 0]
    a, b = math.exp(-2), math.exp(-4)
    assert out == pytest.approx([0.5, 0.5 * a / (2 * a), 0.5 * b / (a + b)])


def test_twins_lone_and_zero_rows(spark):
    twins = points(spark, [(1, 0), (1, 0)], [0, 0])
    assert kernel.pairs(twins, 0.5).first().w == 1.0
    m = retrieval.knn(baselines.raw(twins), baselines.raw(twins), 1).orderBy("query_id").collect()
    assert [(r.query_id, r.match_id, r.dist) for r in m] == [(0, 1, 0.0), (1, 0, 0.0)]
    lone = points(spark, [(1, 0)], [0])
    q = noise.start_matrix(lone, 2)
    assert matrix(contrast_step(q, DenseOp(1.0).over(lone), LabelOp(lone), 0.5)) == pytest.approx(matrix(q))
    ok, bad = features.unit_rows(points(spark, [(0, 0), (3, 4)]))
    assert ok.first().x == pytest.approx([0.6, 0.8]) and bad.count() == 1


def test_empty_inputs(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert features.unit_rows(none)[0].count() == 0
    assert kernel.pairs(none, 1.0).count() == 0 and kernel.laplacian(none, 1.0).count() == 0
    assert retrieval.knn(baselines.raw(none), baselines.raw(none), 3).count() == 0


def test_laplacian_rows_sum_to_zero_and_energy_counts_pairs_once(some):
    lap = kernel.laplacian(some, 0.7)
    assert max(abs(r.s) for r in lap.groupBy("i").agg(F.sum("value").alias("s")).collect()) < 1e-12
    v = noise.start_matrix(some, 3)
    x, y = matrix(some, "x"), matrix(v)
    w = dense(x, 0.7)
    pairs = sum(w[i, j] * ((y[i] - y[j]) ** 2).sum() for i in range(40) for j in range(i))
    assert kernel.energy(v, DenseOp(0.7).over(some)) == pytest.approx(pairs)


@pytest.mark.parametrize("op", [DenseOp(0.7), DenseOp(0.7, block=16, broadcast=0), SparseOp(0.7, theta=0.0)])
def test_products_agree(some, op):
    v = noise.start_matrix(some, 3)
    got = op.over(some).apply(v)
    w = dense(matrix(some, "x"), 0.7)
    assert matrix(got, "wv") == pytest.approx(w @ matrix(v))
    assert matrix(got, "deg") == pytest.approx(w.sum(1))


def test_feature_map_error_falls(some):
    v = noise.start_matrix(some, 3)
    want = dense(matrix(some, "x"), 4.0) @ matrix(v)
    err = [np.linalg.norm(matrix(FeatureMapOp(4.0, r, 5).over(some).apply(v), "wv") - want) for r in (16, 4096)]
    assert err[1] < err[0] / 3


@pytest.mark.parametrize("kind", ["gaussian_code", "same"])
def test_label_product_equals_dense(spark, some, kind):
    v = noise.start_matrix(some, 3)
    rows = some.withColumn("label", F.when(F.col("id") % 5 != 0, F.col("label") * 3))
    y = np.array([np.nan if i % 5 == 0 else (i % 4) * 3 for i in range(40)])
    gap = y[:, None] - y[None]
    w = np.where(np.isnan(gap), 0, np.exp(-(gap**2) / 2.0) if kind == "gaussian_code" else (gap == 0).astype(float))
    np.fill_diagonal(w, 0)
    want = (np.diag(w.sum(1)) - w) @ matrix(v)
    assert matrix(LabelOp(rows, 2.0, kind).apply(v), "lv") == pytest.approx(want)


@pytest.mark.parametrize(("sigma", "alpha"), [(0.3, 0.0), (1.0, 0.5), (4.0, 0.2)])
def test_objective_never_rises_and_majorant_holds(some, sigma, alpha):
    r = run(some, 3, sigma, alpha, 4, monitor=True, keep=True)
    vals = [x["objective"] for x in r.log]
    assert all(b <= a + 1e-9 * abs(a) for a, b in zip(vals, vals[1:], strict=False))
    op, lab = DenseOp(sigma).over(some), LabelOp(some, sigma)
    bound = majorant(r.steps[1], r.steps[0], op, lab, alpha)
    assert bound >= objective(r.steps[1], op, lab, alpha) - 1e-9
    assert bound <= vals[0] + 1e-9
    assert majorant(r.steps[0], r.steps[0], op, lab, alpha) == pytest.approx(vals[0])


def test_alpha_zero_stays_in_range_and_permutes(some):
    r = run(some, 2, 0.5, 0.0, 3, keep=True)
    q, v = matrix(r.steps[0]), matrix(r.v)
    assert (v.max(0) <= q.max(0) + 1e-12).all() and (v.min(0) >= q.min(0) - 1e-12).all()
    again = run(some.repartition(7), 2, 0.5, 0.0, 3).v
    assert matrix(again) == pytest.approx(v)


def test_rescale_keeps_ranks(some):
    a, b = run(some, 2, 0.5, 0.3, 3).v, run(some, 2, 0.5, 0.3, 3, rescale=True)
    assert matrix(a) == pytest.approx(matrix(b.v) * math.exp(0) * (np.linalg.norm(matrix(a)) / np.linalg.norm(matrix(b.v))))


def test_spectral_solves_the_problem(some):
    v, values = spectral(some, 0.7, 3, iterations=200)
    w = dense(matrix(some, "x"), 0.7)
    d = np.diag(w.sum(1))
    half = np.diag(1 / np.sqrt(w.sum(1)))
    want = np.linalg.eigvalsh(half @ (d - w) @ half)[1:4]
    assert values == pytest.approx(want, abs=1e-4)
    y = matrix(v)
    assert y.T @ d @ y == pytest.approx(np.eye(3), abs=1e-8)


def test_sensitivity_bounds_hold(spark):
    rng = np.random.default_rng(0)
    for n, sigma, alpha, extra in ((6, 1.0, 0.5, None), (6, 4.0, 0.1, "twin"), (12, 2.0, 0.5, "far")):
        x = rng.normal(size=(n, 3))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        new = {"twin": x[0], "far": -x[0]}.get(extra, np.array([0, 0, 1.0]))
        p = points(spark, x, [i % 3 for i in range(n)])
        e = points(spark, [new], [1000 if extra == "far" else 1], start=n)
        q = noise.start_matrix(p.select("id").unionByName(e.select("id")), 2)
        gap = sensitivity.observed(p, e, q, sigma, alpha)
        forms = {f: sensitivity.bound_for(n, alpha, sigma, sensitivity.q_norm(q), f, q_spectral=float(np.linalg.norm(matrix(q), 2))) for f in ("uniform", "row_split", "spectral")}
        assert gap <= forms["spectral"] <= forms["row_split"] <= forms["uniform"]
        d = sensitivity.difference(p, e, sigma, alpha).groupBy("i").agg(F.sqrt(F.sum(F.col("value") ** 2)).alias("r")).collect()
        b = sensitivity.row_bounds(n, alpha, sigma)
        assert all(r.r <= (b["new"] if r.i == n else b["old"]) + 1e-12 for r in d)


def test_release_counts_the_start_matrix_of_one_row_more(some):
    """The release itself: its sensitivity is the bound over n + 1 rows of Q, and holds for newcomers with the next id."""
    q = noise.start_matrix(some, 3)
    full = np.r_[matrix(q), arrays.normals(1, np.array([40]), 3)]
    for form in ("uniform", "row_split", "spectral"):
        _, r = release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5, form=form)
        b = sensitivity.row_bounds(40, 0.1, 4.0)
        factor = {"uniform": b["m"] / 2 * math.sqrt(41), "row_split": math.sqrt(40 * b["old"] ** 2 + b["new"] ** 2) / 2}
        factor["spectral"] = factor["row_split"]
        norm = np.linalg.norm(full, 2) if form == "spectral" else np.linalg.norm(full)
        assert r.sensitivity >= factor[form] * norm * (1 - 1e-12)
        assert factor[form] * np.linalg.norm(matrix(q), 2 if form == "spectral" else None) < factor[form] * norm
        new = points(some.sparkSession, [[0, 0, 0, 0, 0, -1.0]], [2], start=40)
        both = noise.start_matrix(some.select("id").unionByName(new.select("id")), 3)
        assert sensitivity.observed(some, new, both, 4.0, 0.1) <= r.sensitivity
    _, tail = release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5, padding="tail")
    assert tail.sensitivity > sensitivity.bound(40, 0.1, 4.0, sensitivity.start_norms(q, 1, 1.0))
    norms = [np.linalg.norm(arrays.normals(s, np.arange(41), 3)) for s in range(200)]
    assert max(norms) < sensitivity.tail_norms(40, 3, 1.0, 1e-6).padded
    with pytest.raises(ValueError, match="does not go"):
        release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5, form="spectral", padding="tail")


def test_barrier_lets_only_the_release_through(spark, some):
    v, _ = release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5)
    secret = sources.cut(some, "secret")
    labels, _, _ = release.published_labels(some, "public")
    assert not release.reads_only(secret, v.at) and not release.reads_only(secret, sources.folder(spark) + "/other")
    barrier = release.Barrier(v.at, labels.at)
    out = release.free_steps(release.resume(spark, v.at), labels, 3, 4.0, 0.1, 2, barrier=barrier)
    assert out.count() == 40 and barrier.check(out) is out
    with pytest.raises(PermissionError):
        release.free_steps(release.resume(spark, v.at), secret.select("id", "label"), 3, 4.0, 0.1, 1, barrier=release.Barrier(v.at))
    with pytest.raises(PermissionError):
        release.Barrier(v.at).cut(release.resume(spark, v.at).join(secret.select("id"), "id"))


def test_exchange_reads_nothing_secret_behind_the_barrier(spark, some):
    p = sources.cut(some.withColumn("role", F.when(F.col("id") < 4, "target").when(F.col("id") % 2 == 0, "public").otherwise("server")), "raw")
    cfg = retrieval.Config(m=3, steps=2, epsilon=0.5, label_policy="randomized", label_epsilon=0.5, calibration="analytic")
    x = retrieval.private_retrieve(p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'"), 3, cfg)
    assert x.report.epsilon == pytest.approx(1.0)
    assert not any(f.startswith(p.at) or p.at.removeprefix("file://") in f for f in x.client.inputFiles())


def test_ledger_is_charged_before_a_release(spark, some, monkeypatch):
    book = ledger.Book(spark, f"{sources.folder(spark)}/book", 1.0)
    release.noisy_first_step(some, 2, 4.0, 0.1, 0.6, 1e-5, book=book)
    assert book.spent("client") == pytest.approx(0.6)
    written = []
    monkeypatch.setattr(release, "cut", lambda *a, **k: written.append(a))
    with pytest.raises(ledger.BudgetExceeded):
        release.noisy_first_step(some, 2, 4.0, 0.1, 0.6, 1e-5, book=book)
    assert not written and book.spent("client") == pytest.approx(0.6)

    def lost(*a, **k):
        raise OSError("disk full")

    monkeypatch.setattr(release, "cut", lost)
    with pytest.raises(OSError, match="disk full"):
        release.noisy_first_step(some, 2, 4.0, 0.1, 0.3, 1e-5, book=book)
    assert book.spent("client") == pytest.approx(0.9)  # paid for, though nothing came of it


def test_iterations_leave_one_table(spark, some):
    """Steps delete what no step reads any more; two lazy results live beside each other."""
    here = pathlib.Path(sources.folder(spark).removeprefix("file://"))
    before = set(here.iterdir())
    a = run(some, 2, 1.0, 0.1, 5, rescale=True).v
    b = run(some, 2, 1.0, 0.1, 3, seed=2, rescale=True).v
    new = [f for f in here.iterdir() if f not in before]
    assert len(new) == 2
    assert a.count() == b.count() == 40
    sources.drop(spark, *(str(f) for f in new))
    assert set(here.iterdir()) == before


def test_a_session_leaves_no_files(tmp_path):
    code = f"""
import sys; sys.path.insert(0, {str(pathlib.Path(__file__).resolve().parents[1])!r})
from pyspark.sql import SparkSession
from manifold_dp import sources
s = SparkSession.builder.master("local[1]").config("spark.ui.enabled", "false").config("spark.checkpoint.dir", "file://{tmp_path}").getOrCreate()
assert sources.cut(s.range(3)).count() == 3
s.stop()
"""
    subprocess.run([sys.executable, "-c", code], check=True, timeout=120, capture_output=True)
    deadline = time.time() + 20
    while list(tmp_path.glob("manifold-*")) and time.time() < deadline:
        time.sleep(0.5)
    assert not list(tmp_path.glob("manifold-*"))


def test_schema_contract(spark, some):
    assert sources.require(some.withColumn("more", F.lit(1)), sources.POINTS).columns == ["id", "x", "label", "role"]
    with pytest.raises(ValueError, match="missing"):
        sources.require(some.drop("x"), sources.POINTS)
    with pytest.raises(ValueError, match="not"):
        sources.require(some.withColumn("id", F.col("id").cast("string")), sources.POINTS)


def test_sweep_equals_the_distributed_operators(spark, sf):
    p = sources.cut(features.feature_set(spark, sf, "emb_planted").where("id % 4 = 0"), "p")
    same = {"set": "p", "m": 4, "seed": 1, "sigma": 0.1, "alpha": 0.1, "steps": 3}
    arms = [same | a for a in ({"method": "raw"}, {"method": "pca"}, {"method": "contrast"}, {"method": "pure_noise", "policy": "masked", "targets": True}, {"method": "contrast", "fold": 1, "folds": 3}, {"method": "trace"}, {"method": "tsne", "iterations": 20}, {"method": "exchange", "epsilon": None})]
    got = sweep.sweep(spark, {"p": p}, arms)
    want = [a | row for a in arms for row in experiments._distributed(p, a)]
    assert len(got) == len(want)
    for g, w in zip(got, want, strict=True):
        for name in w:
            assert g[name] == w[name] if not isinstance(w[name], float) else g[name] == pytest.approx(w[name], rel=1e-6, abs=1e-9), (w["method"], name)


def test_large_forms_equal_small_ones(spark, some):
    v = baselines.raw(some)
    order = ["query_id", "rank"]
    assert retrieval.knn(v, v, 5, sent=0).orderBy(*order).collect() == retrieval.knn(v, v, 5).orderBy(*order).collect()
    assert retrieval.knn(v, v, 5, "cosine", sent=0).orderBy(*order).collect() == retrieval.knn(v, v, 5, "cosine").orderBy(*order).collect()
    with pytest.raises(ValueError, match="rows make"):
        SparseOp(1.0, knn=3, max_pairs=10).over(some)
    words = spark.createDataFrame([(f"w{i % 37:02d}",) for i in range(200)] + [(None,)], "w string")
    assert features.label_codes(words, "w", small=5).orderBy("w").collect() == features.label_codes(words, "w").orderBy("w").collect()


def test_tsne_by_neighbours(some):
    """The form for many rows keeps classes as far apart as the one that holds all pairs."""
    rng = np.random.default_rng(8)
    x = np.repeat(np.eye(6)[:3], 30, 0) + 0.05 * rng.normal(size=(90, 6))
    p = points(some.sparkSession, x / np.linalg.norm(x, axis=1, keepdims=True), [i // 30 for i in range(90)])
    near = baselines.tsne(p, 2, 8, 60, rate=20, exact_rows=10)
    assert near.count() == 90
    assert metrics.precision_at(retrieval.knn(near, near, 5), p, 5) > 0.95


def test_projections_find_most_edges(some):
    """A graph by random projections is a part of the exact one, with the same weights."""
    exact = {(r.i, r.j): r.w for r in SparseOp(1.0, theta=0.3).over(some).edges.collect()}
    found = {(r.i, r.j): r.w for r in SparseOp(1.0, theta=0.3, mode="lsh").over(some).edges.collect()}
    assert found.keys() <= exact.keys() and len(found) > 0.9 * len(exact)
    assert all(w == pytest.approx(exact[k]) for k, w in found.items())


def test_early_stop_ends_at_the_tolerance(some):
    r = run(some, 3, 0.5, 0.0, 30, tol=0.05, rescale=True)
    true = [x["objective"] * math.exp(2 * x["log_scale"]) for x in r.log]
    change = [abs(b - a) / abs(a) for a, b in zip(true, true[1:], strict=False)]
    assert change[-1] <= 0.05 or len(r.log) == 31
    assert all(c > 0.05 for c in change[:-1])


def test_library_text_features_have_unit_length(spark, sf):
    rows = features.ml_text_features(spark, sf, 16).select(F.aggregate("x", F.lit(0.0), lambda s, z: s + z * z).alias("n")).distinct().collect()
    assert all(r.n == pytest.approx(1.0) or r.n == 0.0 for r in rows)


def test_membership_attack_stays_under_its_limit(spark):
    rows = experiments.membership_attack(spark, "/root/testdata/sf0.001", (0.5, 2.0), 200).collect()
    assert all(r.advantage <= r.limit + 0.12 for r in rows)


def test_anchors_of_private_sne_are_a_bounded_part(some):
    p = some.withColumn("role", F.when(F.col("id") < 30, "public").otherwise("server"))
    out = baselines.dp_sne(p, 2, 2.0, 1e-5, iterations=2, max_anchors=10)
    assert out.select("id").distinct().count() == out.count() == 40
    with pytest.raises(ValueError, match="hides nothing"):
        baselines.dp_pca(some, 2, 1.0, 1e-5, test_seed=1)


def test_stream_serves_targets_like_a_batch(spark, sf):
    from manifold_dp import streaming

    p = sources.cut(features.feature_set(spark, sf, "emb_planted").where("id % 3 = 0"), "p")
    cfg = retrieval.Config(m=2, steps=1, epsilon=0.5, calibration="classic", test_noise="n")
    at = f"{sources.folder(spark)}/arriving"
    asked = p.where("role = 'target'").select("id")
    asked.coalesce(1).write.parquet(at)
    s = spark.readStream.schema("id long").parquet(at)
    got = streaming.serve_targets(spark, s, p, cfg).select("query_id", "match_id", "rank")
    want = retrieval.private_retrieve(p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'"), 8, cfg).answers
    assert sorted(map(tuple, got.collect())) == sorted((r.query_id, r.match_id, r["rank"]) for r in want.collect())
    cfg.book = ledger.Book(spark, f"{sources.folder(spark)}/none", 0.1)
    assert streaming.serve_targets(spark, spark.readStream.schema("id long").parquet(at), p, cfg).count() == 0


def test_calibration(spark):
    for eps, delta in ((0.5, 1e-5), (5.0, 1e-6)):
        tau = noise.calibrate(eps, delta, 2.0, "analytic")
        assert noise.trade_off(tau, 2.0, eps) == pytest.approx(delta, rel=1e-6)
    with pytest.warns(UserWarning, match="epsilon < 1"):
        noise.calibrate(2.0, 1e-5, 1.0)
    assert noise.calibrate(0.5, 1e-5, 1.0) > noise.calibrate(0.9, 1e-5, 1.0) > noise.calibrate(0.9, 1e-3, 1.0) > noise.calibrate(0.9, 1e-3, 1.0, "analytic")
    with pytest.raises(ValueError, match="epsilon"):
        noise.calibrate(0.5, 0, 1.0)


def test_release_is_drawn_once(spark, some):
    v, r = release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5)
    w, _ = release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5)
    assert (matrix(v) == matrix(v)).all() and not np.allclose(matrix(v), matrix(w))
    assert (matrix(release.resume(spark, v.at)) == matrix(v)).all()
    step = matrix(contrast_step(noise.start_matrix(some, 3), DenseOp(4.0).over(some), LabelOp(some, 4.0), 0.1))
    gap = (matrix(v) - step).ravel()
    assert 0.75 < gap.std() / r.tau < 1.25
    assert release.reads_only(release.resume(spark, v.at), v.at)
    with pytest.raises(ValueError, match="first iteration"):
        release.noisy_first_step(some, 3, 4.0, 0.1, 0.5, 1e-5, t=2)
    with pytest.raises(ValueError, match="hides nothing"):
        noise.add_test_noise(v, 1.0, 1)


def test_release_refuses_bad_input(spark, some):
    with pytest.raises(ValueError, match="three rows"):
        release.validate(some.limit(2), 1.0, 0.0, 1.0, 1e-5)
    with pytest.raises(ValueError, match="unit length"):
        release.validate(some.withColumn("x", F.transform("x", lambda z: z * 2)), 1.0, 0.0, 1.0, 1e-5)
    with pytest.raises(ValueError, match="rows make"):
        DenseOp(1.0, max_pairs=10).over(some)


def test_label_policies(some):
    p = some.withColumn("role", F.when(F.col("id") < 10, "target").otherwise("public"))
    assert release.labels_for(p, "off")[0].where("label IS NOT NULL").count() == 0
    assert release.labels_for(p, "masked")[0].where("label IS NULL").count() == 10
    same = release.labels_for(p, "randomized", 50.0)[0].withColumnRenamed("label", "l").join(p, "id").where("l <> label").count()
    assert same == 0
    with pytest.raises(ValueError, match="policy"):
        release.labels_for(p, "other")


def test_noise_moments(spark):
    v = noise.add(spark.range(20000).select("id", F.array(*[F.lit(0.0)] * 5).alias("v")), 2.0)
    z = matrix(v).ravel()
    assert abs(z.mean()) < 0.05 and abs(z.std() - 2) < 0.03 and abs((z**4).mean() / (z**2).mean() ** 2 - 3) < 0.15


def test_alignment_recovers_motion(spark):
    rng = np.random.default_rng(1)
    a = rng.normal(size=(30, 3))
    r = np.linalg.qr(rng.normal(size=(3, 3)))[0]
    r *= np.sign(np.linalg.det(r))
    t = np.array([1.0, -2.0, 0.5])
    df = lambda m: spark.createDataFrame([(i, [float(z) for z in row]) for i, row in enumerate(m)], "id long, v array<double>")
    m = align.fit(df(a), df(a @ r + t))
    assert m.rotation == pytest.approx(r, abs=1e-12) and m.shift == pytest.approx(t, abs=1e-12)
    assert align.rmsd(align.apply(df(a), m), df(a @ r + t)) < 1e-12
    s = align.fit(df(a), df(2.5 * a @ r), scale=True)
    assert s.scale == pytest.approx(2.5)
    mirror = a * np.array([1, 1, -1])
    assert np.linalg.det(align.fit(df(a), df(mirror)).rotation) == pytest.approx(1)
    assert align.rmsd(align.apply(df(a), align.fit(df(a), df(mirror), reflect=True)), df(mirror)) < 1e-12


def test_dummies_ask_every_class_once(some):
    p = some.withColumn("role", F.when(F.col("id") < 3, "target").otherwise("public"))
    t, u = p.where("role = 'target'"), p.where("role = 'public'")
    d = retrieval.dummies(t, u)
    for r in t.collect():
        asked = sorted([r.label, *(x.label for x in d.where(F.col("target_id") == r.id).collect())])
        assert asked == [0, 1, 2, 3]
    c = retrieval.client_set(t, u, d)
    assert c.count() == c.select("id").distinct().count() == 40
    assert retrieval.client_set(t, u, d, keep_dummy_anchor=True).where("role = 'public'").count() == 37


def test_exchange_finds_planted_classes(spark):
    rng = np.random.default_rng(5)
    n, k = 120, 4
    lab = [i % k for i in range(n)]
    x = 0.15 * rng.normal(size=(n, 8))
    for i in range(n):
        x[i, lab[i]] += 1
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    role = ["target" if i < 8 else "public" if i // 4 % 2 else "server" for i in range(n)]
    p = points(spark, x, lab, role).cache()
    cfg = retrieval.Config(m=16, sigma=0.3, alpha=0.0, steps=6, private=False)
    got = retrieval.private_retrieve(p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'"), 5, cfg)
    assert metrics.precision_at(got.answers, p, 5) > 0.9
    assert got.rmsd_after <= got.rmsd_before
    assert {r.query_id for r in got.answers.collect()} == set(range(8))
    private = retrieval.private_retrieve(p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'"), 5, retrieval.Config(m=4, steps=2, alpha=0.1))
    assert private.answers.count() == 40 and private.report.label_policy == "masked"


def test_linear_baselines(some, spark):
    x = matrix(some, "x")
    v = matrix(baselines.pca(some, 3))
    top = np.linalg.eigh(x.T @ x)[1][:, ::-1][:, :3]
    assert np.abs(v) == pytest.approx(np.abs(x @ top))
    noisy = matrix(baselines.dp_pca(some, 3, 1e7, 1e-3, target="directions"))
    assert np.abs(noisy) == pytest.approx(np.abs(v), abs=1e-3)
    r = baselines.projection_matrix(6, 3, 7)
    assert matrix(baselines.random_projection(some, 3)) == pytest.approx(x @ r)
    assert baselines.second_moment(some, centred=True) == pytest.approx((x - x.mean(0)).T @ (x - x.mean(0)))


def test_tsne_falls_and_dp_sne_accounts(some):
    log: list = []
    v = baselines.tsne(some, 2, 8, 160, log=log, rate=20)
    assert v.count() == 40 and log[-1] < log[101]
    p = some.withColumn("role", F.when(F.col("id") % 2 == 0, "public").otherwise("server"))
    book: list = []
    out = baselines.dp_sne(p, 2, 2.0, 1e-5, iterations=3, ledger=book)
    assert out.count() == 40 and book[0]["epsilon_rounds"] == pytest.approx(1.0)


def test_ledger_is_exact(spark):
    none = spark.createDataFrame([], ledger.SCHEMA)
    who = spark.createDataFrame([("a",), ("b",)], "subject string")
    book = ledger.charge(none, who, "first", 0.1, 1e-6, 1.0, "2024-01-01")
    book = ledger.charge(book, who.limit(1), "second", 0.2, 1e-6, 1.0, "2024-01-02")
    assert {r.subject: str(r.epsilon) for r in ledger.spent(book).collect()} == {"a": "0.300000000", "b": "0.100000000"}
    assert [r.ok for r in ledger.allowed(book, 0.25).orderBy("subject", "at").collect()] == [True, False, True]


def test_measures(some):
    v = baselines.raw(some)
    exact = retrieval.knn(v, v, 8)
    assert metrics.set_recall(exact, exact, 8).agg(F.min("recall")).first()[0] == 1.0
    assert metrics.set_recall(retrieval.knn_buckets(v, v, 8, 4, 4), exact, 8).agg(F.min("recall")).first()[0] == 1.0
    one = metrics.recall_at(exact, some, 8)
    assert metrics.precision_at(exact, some, 8) <= one <= 1
    assert metrics.membership([1, 2, 3], [4, 5, 6]) == 1.0
    assert metrics.distortion(noise.start_matrix(some, 2), some, 1.0).count() == 780


def test_gram(some):
    v = noise.start_matrix(some, 3)
    assert gram(v) == pytest.approx(matrix(v).T @ matrix(v))


def test_experiments_take_every_row(spark, sf):
    """Sets of over 500 rows are whole in the workloads."""
    from manifold_dp.plans import methods

    n = features.feature_set(spark, sf, "doc_lang").count()
    assert n > 500
    assert {r.queries for r in methods.QUERIES["baseline_raw"](spark, sf).collect()} == {n}


def test_workloads_are_registered_whole(monkeypatch):
    """Every set, seed and value of SURVEY 2.8, with the private grid beside the other."""
    import inspect

    from manifold_dp.operators import experiments
    from manifold_dp.plans import methods

    def asked(query, function):
        real, got = inspect.signature(getattr(experiments, function)), []
        monkeypatch.setattr(experiments, function, lambda *a, **kw: got.append(real.bind(*a, **kw)))
        methods.QUERIES[query](None, "")
        got[0].apply_defaults()
        return got[0].arguments

    three = {"emb_planted", "doc_lang", "page_lang"}
    w2, w4, w7 = asked("w2_convergence", "convergence"), asked("w4_privacy_utility", "privacy_utility"), asked("w7_cost", "cost")
    assert set(w2["sets"]) == set(w4["sets"]) == three
    assert w2["steps"] == 10 and len(w4["seeds"]) >= 5
    assert w4["epsilons"] == (0.1, 0.5, 1.0, 5.0, 10.0, 100.0, 1000.0)
    assert w4["rows"] is None and w7["copies"] is None
    assert experiments.growing(2000) == (1, 4, 16, 64, 256, 500)
    for query, private in (("w3_parameters", False), ("w3_private_parameters", True)):
        monkeypatch.undo()
        w3 = asked(query, "grid")
        assert w3["private"] is private and w3["rows"] is None
        assert [len(w3[k]) for k in ("ms", "alphas", "sigmas")] == [5, 5, 5]


def test_copies_are_not_broadcast(some):
    graph = kernel.SparseOp(1.0, knn=3).over(some).edges
    p, v, e = experiments._copies(some, graph, 3, 2)
    for op in (kernel.FeatureMapOp(1.0, 8), kernel.SparseOp(1.0, knn=3, edges=e)):
        got = op.over(p).apply(v)
        assert "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()
        assert got.count() == 3 * some.count()


def test_products_both_ways(some, monkeypatch):
    """Weights that serve both their rows give the same products, and the objective counted with a step is that of its rows."""
    p = sources.cut(some, "some")
    v = experiments.known_width(p.select("id", F.slice("x", 1, 3).alias("v")), 3)
    for of in (v, None):
        got, want = (op.over(p).apply(of) for op in (DenseOp(0.7, both_ways=1), DenseOp(0.7)))
        for col in ("v", "wv"):
            assert np.allclose(matrix(got, col), matrix(want, col), atol=1e-12)
        assert [r.deg for r in got.orderBy("id").collect()] == pytest.approx([r.deg for r in want.orderBy("id").collect()])
    r = run(p, 3, 0.7, 0.1, 2, monitor=True, keep=True)
    labels = LabelOp(p, 0.7, "gaussian_code")
    assert [x["objective"] for x in r.log] == pytest.approx([objective(s, DenseOp(0.7).over(p), labels, 0.1) for s in r.steps])
    x, y = matrix(p, "x"), matrix(v)
    whole = arrays.Graph(x, 0.7).apply(y)
    monkeypatch.setattr(arrays, "ENTRIES", 1)
    monkeypatch.setattr(arrays, "SIDE", 7)
    assert all(np.allclose(a, b) for a, b in zip(arrays.Graph(x, 0.7).apply(y), whole, strict=True))


def test_small_sets_are_swept_beside_large_ones(spark, some, monkeypatch):
    p = sources.cut(some, "some")
    calls = []
    monkeypatch.setattr(experiments, "fits", lambda sets: "large" not in sets)
    monkeypatch.setattr(experiments, "_distributed", lambda points, a: calls.append(a["set"]) or [{"recall_at_8": 0.0}])
    arms = [{"set": name, "method": "raw"} for name in ("small", "large")]
    got = experiments.measured(spark, {"small": p, "large": p}, arms)
    assert calls == ["large"] and [g["set"] for g in got] == ["small", "large"] and got[0]["recall_at_8"] > 0


def test_search_of_crowded_rows(monkeypatch):
    """Rows closer than single precision tells apart, beside far ones: few pairs are measured, and the answers are exact."""
    rng = np.random.default_rng(4)
    x = np.r_[1 + 1e-3 * rng.normal(size=(600, 3)), 40 * rng.normal(size=(4, 3))]
    x[5] = x[9]
    ids, seen, measured = np.arange(604) * 3, [], arrays.measured
    monkeypatch.setattr(arrays, "measured", lambda a, b, at, col: seen.append(len(at)) or measured(a, b, at, col))
    found, dist = arrays.nearest(ids, x, ids, x, 3)
    gaps = np.round(((x[:, None] - x[None]) ** 2).sum(2), 12)
    np.fill_diagonal(gaps, np.inf)
    order = np.lexsort((np.broadcast_to(ids, gaps.shape), gaps), axis=1)[:, :3]
    assert (found == ids[order]).all() and np.array_equal(dist, np.take_along_axis(gaps, order, 1))
    assert sum(seen) < 20 * len(x)


def test_repulsion_of_all_pairs_on_a_grid(some, monkeypatch):
    rng = np.random.default_rng(6)
    for scale in (1e-4, 1.0, 12.0):
        y = scale * rng.normal(size=(700, 2))
        q = 1 / (1 + arrays.square_gaps(y, y))
        np.fill_diagonal(q, 0)
        want = (q * q).sum(1)[:, None] * y - (q * q) @ y
        got, total = arrays.repulsion(y)
        assert total == pytest.approx(q.sum(), rel=1e-8) and np.abs(got - want).max() < 1e-7 * np.abs(want).max()
    near = matrix(baselines.tsne(some, 2, 8, 15, rate=20, exact_rows=10))
    monkeypatch.setattr(arrays, "WIDE", -1.0)
    assert np.abs(near - matrix(baselines.tsne(some, 2, 8, 15, rate=20, exact_rows=10))).max() < 1e-5


def test_wide_blocks_need_fewer_products(spark, monkeypatch):
    x = np.random.default_rng(9).normal(size=(300, 5))
    p = sources.cut(points(spark, x / np.linalg.norm(x, axis=1, keepdims=True)), "p")
    from manifold_dp.operators import maps

    made, cut = [], maps.cut
    monkeypatch.setattr(maps, "cut", lambda df, name="t": made.append(name) or cut(df, name))
    values = spectral(p, 1.0, 3)[1]
    wide, made[:] = made.count("product"), []
    assert values == pytest.approx(spectral(p, 1.0, 3, block=4)[1], abs=1e-9) and wide < made.count("product")


def test_equal_runs_without_noise_are_one(spark, some, monkeypatch):
    calls = []
    monkeypatch.setattr(experiments, "fits", lambda sets: not sets)
    monkeypatch.setattr(experiments, "_distributed", lambda points, a: calls.append(a["method"]) or [{"recall_at_8": float(len(calls))}])
    arms = [{"set": "p", "method": method, "moved": moved, "seed": 1} for method in ("contrast", "release") for moved in ("m", "alpha", "sigma")]
    got = experiments.measured(spark, {"p": some}, arms)
    assert calls == ["contrast", "release", "release", "release"]
    assert [(g["moved"], g["recall_at_8"]) for g in got] == [("m", 1.0), ("alpha", 1.0), ("sigma", 1.0), ("m", 2.0), ("alpha", 3.0), ("sigma", 4.0)]


def test_equal_points_meet_others_as_one(spark, monkeypatch):
    """Copies have their weights and sums from one product of the distinct points, also where some rows have no v."""
    x = np.random.default_rng(3).normal(size=(12, 4))[np.arange(40) % 12]
    x[39] = 5.0
    p = sources.cut(points(spark, x), "p")
    v = experiments.known_width(p.select("id", F.array(F.sin(F.col("id") * 1.0), F.cos(F.col("id") * 2.0)).alias("v")), 2)
    for of in (v, v.where("id > 3"), None):
        met = DenseOp(0.7, both_ways=1).over(p)
        assert met.met.n == 13
        got, want = met.apply(of), DenseOp(0.7).over(p).apply(of)
        for col in ("v", "wv"):
            assert np.allclose(matrix(got, col), matrix(want, col), rtol=1e-12, atol=1e-12)
        assert [r.deg for r in got.orderBy("id").collect()] == pytest.approx([r.deg for r in want.orderBy("id").collect()])


def test_controls_search_every_twentieth_row(spark, sf, monkeypatch):
    """A sweep and the distributed operators ask for the same rows: those whose id is divisible by 20."""
    p = sources.cut(features.feature_set(spark, sf, "emb_raw"), "p")
    arms = [{"set": "p", "method": method, "m": 4, "sigma": 0.1, "alpha": 0.0, "steps": 2, "every": 20} for method in ("raw", "contrast")]
    asked, knn = [], experiments.retrieval.knn
    monkeypatch.setattr(experiments.retrieval, "knn", lambda q, *rest: asked.append(q.select("id").collect()) or knn(q, *rest))
    swept = experiments.measured(spark, {"p": p}, arms)
    monkeypatch.setattr(experiments, "fits", lambda sets: not sets)
    far = experiments.measured(spark, {"p": p}, arms)
    assert len(asked) == 2 and all(ids and all(r.id % 20 == 0 for r in ids) for ids in asked)
    for a, b in zip(swept, far, strict=True):
        assert a == pytest.approx(b)


def test_exchanges_share_the_servers_runs(spark, sf, monkeypatch):
    """Four exchanges have two servers, made on one graph; all measures are those of a sweep, and no set's size leaves one out."""
    p = sources.cut(features.feature_set(spark, sf, "emb_planted").where("id < 90"), "p")
    arms = [{"set": "p", "method": "exchange", "m": 3, "sigma": 4.0, "alpha": alpha, "steps": 2, "delta": 1e-5, "epsilon": eps, "seed": 1} for eps in (None, 1e12) for alpha in (0.0, 0.5)]
    swept = experiments.measured(spark, {"p": p}, arms)
    made, many = [], retrieval.run_many
    monkeypatch.setattr(retrieval, "run_many", lambda *a: made.append(a[3]) or many(*a))
    monkeypatch.setattr(experiments, "fits", lambda sets: not sets)
    far = experiments.measured(spark, {"p": p}, arms)
    assert made == [[(0.0, "1s"), (0.5, "1s")]]
    for a, b in zip(swept, far, strict=True):
        assert set(a) == set(b)
        values = ("rmsd_before", "rmsd_after", "relative_after", "precision_at_8", "recall_at_8")
        assert a["epsilon"] is not None or [a[n] for n in values] == pytest.approx([b[n] for n in values], rel=1e-6)
        assert b["relative_after"] > 0
