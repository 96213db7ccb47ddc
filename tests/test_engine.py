"""Golden values, properties and shapes of the private-recognition engine."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from eigenveil import sources
from eigenveil.functions import laplace_icdf, register
from eigenveil.operators import attack, audit, baselines, classify, cohort, imaging, measures, moments, noise, project, release, scaling, spectra
from eigenveil.params import ReleaseParams, cap_components, check_budget, resolve_target
from eigenveil.plans import workloads


def grid(spark, rows, w, h, labels=None):
    data = [(i, labels[i] if labels else "a", w, h, 1, [float(v) for v in x]) for i, x in enumerate(rows)]
    return spark.createDataFrame(data, sources.IMAGE)


@pytest.mark.parametrize("mins, want", [((40, 50), (47, 62)), ((50, 60), (50, 60)), ((40, 70), (40, 70)), ((50, 70), (50, 70))])
def test_target_rule(mins, want):
    assert resolve_target(47, 62, *mins) == want


def test_component_cap():
    assert [cap_components(n, 47, 62) for n in (10, 47, 48, 63, 128)] == [10, 47, 47, 47, 47]
    assert cap_components(128, 47, 62, enforce=False) == 128


def test_budget_limits():
    assert check_budget(None) is None and check_budget(9) == 9.0
    assert check_budget(100, allow_extreme=True) == 100.0
    for bad in (0, -1, 9.5):
        with pytest.raises(ValueError):
            check_budget(bad)


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 6), min_size=1, max_size=6), st.integers(0, 10_000))
def test_merge_is_exact_for_any_parts(sizes, seed):
    rng = np.random.default_rng(seed)
    parts = [rng.normal(size=(n, 3)) for n in sizes]
    whole = np.concatenate(parts)
    for got in (moments.merge_chain([moments.Moments.of(p) for p in parts]), moments.merge_tree([moments.Moments.of(p) for p in parts[::-1]])):
        assert got.n == len(whole)
        if len(whole) > 1:
            assert np.allclose(got.covariance(), np.cov(whole.T), atol=1e-10)


def test_printed_rule_is_not_exact():
    rng = np.random.default_rng(0)
    a, b = rng.normal(size=(30, 2)), rng.normal(size=(50, 2)) + 1
    pooled = np.cov(np.concatenate([a, b]).T)
    m = [moments.Moments.of(x) for x in (a, b)]
    assert np.allclose(moments.merge_pair(*m).covariance(), pooled)
    assert measures.merge_error(moments.merge_pair(*m, "as_printed").covariance(), pooled) > 0.1
    with pytest.raises(ValueError):
        moments.merge_pair(moments.Moments.of(a[:1]), m[1], "as_printed")


def test_rounds_and_routes_agree(spark, sf):
    base = sources.planted_faces(sources.table(spark, sf, "embeddings"))
    x = np.array([r.px for r in base.orderBy("id").collect()], np.float64)
    assert np.allclose(moments.covariance_one_round(base.repartition(7)), np.cov(x.T), atol=1e-12)
    assert np.allclose(moments.covariance_two_round(base), np.cov(x.T), atol=1e-12)
    local = spectra.fit_local(x, 8)
    for model in (spectra.fit(base, 8, route="direct"), spectra.solve_gram(base, 8), spectra.solve_subspace(base, 8, iters=60, tol=1e-12)):
        assert np.allclose(model.values, local.values, atol=1e-6)
        assert spectra.same_subspace(model.vectors, local.vectors) < 1e-4
    checks = spectra.eigen_checks(np.cov(x.T), spectra.fit_local(x, 64))
    assert checks["residual"] < 1e-10 and checks["orthonormal"] < 1e-10 and abs(checks["share"] - 1) < 1e-10


def test_hand_eigenpairs(spark):
    model = spectra.fit_local(np.array([[2.0, 0, 0, 0], [-2, 0, 0, 0], [0, 1, 0, 0], [0, -1, 0, 0]]), 2)
    assert np.allclose(model.values, [8 / 3, 2 / 3]) and np.allclose(model.vectors, [[1, 0, 0, 0], [0, 1, 0, 0]])


def test_plan_route():
    assert [spectra.plan_route(n, d) for n, d in ((100, 2914), (10**9, 2914), (10**9, 29103))] == ["gram", "direct", "subspace"]


def test_images(spark):
    df = grid(spark, [[1, 2, 3, 4, 5, 6]], 2, 3)
    assert imaging.vertical_flip(df).first().px == [5, 6, 3, 4, 1, 2]
    assert imaging.vertical_flip(imaging.vertical_flip(df)).first().px == [1, 2, 3, 4, 5, 6]
    assert imaging.resample(df, 1, 1, "area").first().px == [3.5]
    for kernel in ("nearest", "bilinear", "area"):
        assert imaging.resample(df, 2, 3, kernel).first().px == [1, 2, 3, 4, 5, 6]
    rgb = spark.createDataFrame([(1, "a", 1, 2, 3, [1.0, 2.0, 4.0, 5.0, 7.0, 8.0])], sources.IMAGE)
    assert imaging.to_gray(rgb).first().px == [4.0, 5.0]
    assert imaging.standardise(df, "unit_range").first().px == pytest.approx([0, 0.2, 0.4, 0.6, 0.8, 1.0])
    z = imaging.standardise(df, "zscore").first().px
    assert np.mean(z) == pytest.approx(0, abs=1e-6) and np.std(z) == pytest.approx(1, abs=1e-6)
    good, bad = imaging.split_valid(spark.createDataFrame([(1, "a", 1, 2, 1, [1.0, 2.0]), (2, "a", 1, 2, 1, None), (3, "a", 1, 2, 1, [1.0]), (4, "a", 1, 2, 1, [1.0, float("nan")])], sources.IMAGE))
    assert good.count() == 1 and {r.reason for r in bad.collect()} == {"null", "length", "not finite"}


def test_bitmaps(spark, tmp_path):
    (tmp_path / "ann").mkdir()
    (tmp_path / "ann" / "a.pgm").write_bytes(b"P5\n# made\n2 2\n255\n" + bytes([0, 50, 100, 150]))
    (tmp_path / "ann" / "b.ppm").write_bytes(b"P6 1 1 255\n" + bytes([9, 8, 7]))
    rows = {r.ch: r for r in sources.images(spark, str(tmp_path)).collect()}
    assert rows[1].px == [0, 50, 100, 150] and rows[3].px == [9, 8, 7] and rows[1].label == "ann"
    spark.dataSource.register(sources.FaceGridSource)
    made = spark.read.format("facegrid").option("rows", 12).option("persons", 3).load()
    assert made.count() == 12 and made.select("label").distinct().count() == 3


def test_cohort(spark):
    labels = ["a"] * 5 + ["b"] * 3 + ["c"]
    df = grid(spark, [[i, 0] for i in range(9)], 2, 1, labels)
    assert {r.label for r in cohort.keep_frequent(df, 3).collect()} == {"a", "b"}
    capped = {r.label: r["count"] for r in cohort.cap_per_class(df, 3).groupBy("label").count().collect()}
    assert capped == {"a": 3, "b": 3, "c": 1}
    assert "c" not in {r.label for r in cohort.cap_per_class(df, 3, mode="exact").collect()}
    parts = cohort.split(df)
    assert parts.where("split = 'train'").select("id").intersect(parts.where("split = 'test'").select("id")).count() == 0


def test_published_cohort_counts(spark):
    """Class sizes 236, 121, 530, 109, 144 pass a threshold of 100; 70 % of 1,140 is 798."""
    sizes = [236, 121, 530, 109, 144, 99, 3]
    df = spark.createDataFrame([(i * 1000 + k, f"p{i}") for i, n in enumerate(sizes) for k in range(n)], "id long, label string")
    kept = cohort.keep_frequent(df, 100)
    assert kept.count() == 1140 and kept.select("label").distinct().count() == 5
    assert abs(cohort.split(kept, stratify="label").where("split = 'train'").count() - 798) <= 2


def test_projection_round_trip(spark, sf):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = spectra.fit(base, 64)
    back = project.synthesise(project.scores(base.select("id", "px"), model), model)
    pairs = back.join(base, "id").select("face", "px").collect()
    assert max(np.abs(np.array(r.face) - np.array(r.px)).max() for r in pairs) < 1e-6
    with pytest.raises(Exception, match="entries"):
        project.scores(grid(spark, [[1, 2]], 2, 1), model).collect()


def test_scaling_constant_and_clip(spark):
    df = spark.createDataFrame([(1, [0.0, 5.0]), (2, [2.0, 5.0]), (3, [1.0, 5.0])], "id long, score array<double>")
    bounds = scaling.fit_bounds(df)
    got = {r.id: r.s for r in df.select("id", scaling.scaled("score", bounds).alias("s")).collect()}
    assert got == {1: [0.0, 0.5], 2: [1.0, 0.5], 3: [0.5, 0.5]}
    outside = spark.createDataFrame([(1, [9.0, 5.0])], "id long, score array<double>")
    assert outside.select(scaling.scaled("score", bounds).alias("s")).first().s[0] == 1.0


def test_laplace_quantiles(spark):
    row = spark.range(1).select(*[laplace_icdf(F.lit(u), 0.25).alias(f"q{k}") for k, u in enumerate((0.25, 0.5, 0.75))]).first()
    assert row.q0 == pytest.approx(-0.25 * math.log(2)) and row.q1 == 0 and row.q2 == pytest.approx(0.25 * math.log(2))
    assert noise.sensitivity(128) == 1 and noise.sensitivity(128, "euclidean") == pytest.approx(11.3137, abs=1e-4) and noise.sensitivity(128, "l1") == 128
    assert 128 * 8 / noise.sensitivity(128, "euclidean") == pytest.approx(90.5, abs=0.02)


def test_noise_law_and_ratio(spark, sf):
    draws = spark.range(4000).select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: laplace_icdf(noise.keyed_uniform("k", F.col("id").cast("string"), i.cast("string")), 0.25))).alias("z"))
    m = audit.noise_moments(draws).first()
    assert m.mean_abs == pytest.approx(0.25, rel=0.03) and m.variance == pytest.approx(0.125, rel=0.06)
    assert audit.ks_laplace(draws, 4.0).first().ks < 1.63 / math.sqrt(32000)
    assert all(r.holds for r in audit.ldp_ratio(spark, 4.0, 1.0, [(0.0, 1.0), (0.2, 0.3)]).collect())


def test_gaussian_sigma_is_enough():
    assert noise.gaussian_sigma(0.5, 1e-5, 1.0) == pytest.approx(math.sqrt(2 * math.log(1.25e5)) / 0.5)
    assert noise.gaussian_sigma(4.0, 1e-5, 1.0) < noise.gaussian_sigma(1.0, 1e-5, 1.0)


def test_release_is_reproducible_and_guarded(spark, sf, tmp_path):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = release.PrivateEigenRelease(ReleaseParams(nc=8, eps=8.0, key="k1", irw=8, irh=8)).fit(base)
    frame = model.release(base)
    assert frame.eps_index == 8 and frame.eps_record == 64
    one = {r.id: r.pv for r in release.assert_released(frame).collect()}
    again = {r.id: r.pv for r in model.release(base.repartition(9)).df.collect()}
    assert all(np.allclose(one[i], again[i], atol=1e-9) for i in one)
    other = {r.id: r.pv for r in model.release(base, release_id="r2").df.collect()}
    assert all(one[i] != other[i] for i in one)
    clean = {r.id: r.pv for r in baselines.no_privacy(model, base).df.collect()}
    train = {r.id for r in cohort.split(base).where("split = 'train'").collect()}
    assert all(-1e-9 <= v <= 1 + 1e-9 for i in train for v in clean[i])
    with pytest.raises(ValueError):
        release.assert_released(release.ReleasedFrame(model.scaled(base), 8.0, 1.0, 8, "x", "r"))
    with pytest.raises(TypeError):
        release.assert_released(base)
    with pytest.raises(ValueError):
        release.export({"edge": model}, str(tmp_path / "m"), spark)
    release.save(model, str(tmp_path / "edge"), spark)
    again = release.load(spark, str(tmp_path / "edge"))
    same = {r.id: r.pv for r in again.release(base).df.collect()}
    assert all(np.allclose(one[i], same[i], atol=1e-9) for i in one)
    release.publish(frame, str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == base.count()


def test_release_does_not_shuffle(spark, sf):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = release.PrivateEigenRelease(ReleaseParams(nc=8, eps=8.0, key="k1", irw=8, irh=8)).fit(base)
    assert measures.cost_counters(model.release(base).df)["exchanges"] == 0


def test_metrics_by_hand(spark):
    rows = [("a", "a")] * 3 + [("a", "b")] + [("b", "b")] * 2 + [("c", "a")] * 2
    df = spark.createDataFrame(rows, "label string, pred string")
    by = {r["class"]: r for r in measures.class_report(df).collect()}
    assert by["a"].precision == pytest.approx(0.6) and by["a"].recall == pytest.approx(0.75) and by["c"].f1 == 0
    w = measures.weighted_report(df).first()
    assert w.n == 8 and w.recall == pytest.approx(5 / 8) and w.precision == pytest.approx((4 * 0.6 + 2 * 2 / 3) / 8)
    curve = spark.createDataFrame([(i, 1.0 / i if i < 5 else 0.25) for i in range(1, 30)], "epoch int, loss double")
    assert measures.epochs_to_converge(curve).first().epochs == 4


def test_perceptron_gradient_is_the_same_in_parts(spark, sf):
    base = sources.planted_faces(sources.table(spark, sf, "embeddings")).select("id", "label", F.col("px").cast("array<double>").alias("pv"))
    x, y, classes = classify.gather(base)
    net = classify.Perceptron.fresh(64, (16,), classes, 1)
    loss, grads = net.gradient(x, y)
    for parts in (1, 5):
        got_loss, n, got = classify.mlp_gradient(base.repartition(parts), net)
        assert n == len(x) and got_loss == pytest.approx(loss, rel=1e-4)
        assert np.allclose(got[0][0], grads[0][0], atol=1e-2)
    trained = classify.mlp_fit_parallel(base, hidden=(16,), steps=8)
    assert trained.losses[-1] < trained.losses[0]
    fitted = classify.mlp_fit(base, hidden=(32,), max_iter=30)
    assert measures.accuracy(classify.predict(base, fitted)).first().accuracy > 0.9
    assert measures.accuracy(classify.predict(base, classify.nearest_fit(base))).first().accuracy == 1.0


def test_encrypted_match_equals_plain(spark, sf):
    keys = baselines.Paillier.fresh(128)
    import random

    rng = random.Random(2)
    a, b = keys.encrypt(20, rng), keys.encrypt(-50, rng)
    assert keys.decrypt(keys.add(a, keys.times(b, 3))) == -130
    base = sources.embedding_images(sources.table(spark, sf, "embeddings")).orderBy("id").limit(5)
    model = spectra.fit(base, 3)
    inter, packed = (baselines.encrypted_match(base, base, model, v).orderBy("id").collect() for v in ("interactive", "packed"))
    assert [r.match for r in inter] == [r.id for r in inter] == [r.match for r in packed]
    assert sum(r.decryptions for r in packed) < sum(r.decryptions for r in inter)


def test_k_average_groups(spark, sf):
    got = baselines.k_average(sources.embedding_images(sources.table(spark, sf, "embeddings")), 5)
    sizes = [r["count"] for r in got.groupBy("grp").count().collect()]
    assert min(sizes) >= 5 and got.groupBy("grp").agg(F.countDistinct("pv").alias("n")).agg(F.max("n")).first()[0] == 1


def test_attack_recovers_without_noise(spark, sf):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = spectra.fit(base, 64)
    clean = project.centred(base.select("id", "px"), model.mean, out="pv")
    guessed = attack.reconstruct(clean, model, add_mean=True).join(base.select("id", F.col("px").cast("array<double>").alias("px")), "id")
    assert measures.reconstruction(guessed).agg(F.max("mse")).first()[0] < 1e-10
    scored = spark.createDataFrame([(0.9, True), (0.8, True), (0.4, False), (0.85, False)], "confidence double, member boolean")
    assert attack.membership(scored).first().advantage == pytest.approx(0.5)
    rows = spark.createDataFrame([("a", "a", 0.9), ("a", "b", 0.6)], "label string, pred string, confidence double")
    assert attack.memorisation_gap(rows.where("pred = 'a'"), rows).first().accuracy_gap == pytest.approx(0.5)


def test_sql_functions(spark):
    register(spark)
    row = spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)) AS d, vec_l1(array(1D, 2D), array(3D, 5D)) AS a, vec_l2(array(0D, 0D), array(3D, 4D)) AS e, vec_scale01(array(5D, 1D), array(0D, 1D), array(10D, 1D)) AS s, vec_sub(array(1D), array(3D)) AS m, laplace_pdf(0D, 0D, 0.25D) AS p").first()
    assert (row.d, row.a, row.e, row.s, row.m, row.p) == (11, 5, 5, [0.5, 0.5], [-2.0], 2.0)
    assert spectra.choose_nc([(10, 0.7), (20, 0.9), (40, 0.905), (80, 0.906)]) == 20


def test_empty_and_bad_inputs(spark):
    empty = spark.createDataFrame([], sources.IMAGE)
    with pytest.raises(ValueError):
        spectra.fit(empty, 2)
    with pytest.raises(ValueError):
        release.PrivateEigenRelease(ReleaseParams(nc=2, eps=1.0, key="k")).fit(empty)
    with pytest.raises(Exception, match="one length"):
        moments.moments(spark.createDataFrame([([1.0],), ([1.0, 2.0],)], "px array<float>").coalesce(1))


def test_nearest_rate_has_no_bound(spark):
    """Over 5,000 rows in the gallery, and small blocks against one block and brute force."""
    rng = np.random.default_rng(8)
    x = rng.normal(size=(5_200, 4))
    noisy = x[:700] + rng.normal(size=(700, 4)) * 0.1
    a = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(noisy)], "id long, pv array<double>")
    b = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, pv array<double>")
    near = ((noisy[:, None] - x[None]) ** 2).sum(2).argmin(1)
    for size in (4 << 20, 16_384 * 4):
        got = attack.nearest_rate(a, b, "pv", block_bytes=size).first()
        assert got.n == 700 and got.rate == pytest.approx((near == np.arange(700)).mean())
    assert attack.link(b, b).first().rate == 1.0


def test_perceptron_beyond_the_bound(spark, sf):
    base = sources.planted_faces(sources.table(spark, sf, "embeddings")).select("id", "label", F.col("px").cast("array<double>").alias("pv"))
    net = classify.mlp_fit(base, hidden=(32,), max_iter=30, limit=100)
    assert len(net.losses) == 30 and net.losses[-1] < net.losses[0]
    assert measures.accuracy(classify.predict(base, net)).first().accuracy > 0.9


def test_guard_reads_the_plan(spark, sf):
    """A raw column does not leave under another name, nor does any other vector."""
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = release.PrivateEigenRelease(ReleaseParams(nc=4, eps=8.0, key="k", irw=8, irh=8, enforce_cap=False)).fit(base)
    frame = model.release(base)
    assert release.assert_released(frame).columns == ["id", "label", "pv"]
    for leak in (model.scaled(base).select("id", F.col("scaled").alias("pv")), base.select("id", F.col("px").alias("x")).select("id", F.col("x").alias("pv")), base.select("id", F.col("px").alias("other"))):
        with pytest.raises(ValueError):
            release.assert_released(release.ReleasedFrame(leak, 8.0, 1.0, 4, "x", "r"))


def test_bad_rows_are_rejected_with_reasons(spark, sf):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    bad = base.withColumn("px", F.when(F.col("id") == 3, F.lit(None)).when(F.col("id") == 4, F.slice("px", 1, 9)).when(F.col("id") == 5, F.transform("px", lambda x: F.lit(float("nan")).cast("float"))).otherwise(F.col("px")))
    model = release.PrivateEigenRelease(ReleaseParams(nc=4, eps=8.0, key="k", irw=8, irh=8, enforce_cap=False)).fit(bad)
    want = {(3, "null"), (4, "length"), (5, "not finite")}
    assert {tuple(r) for r in model.rejected.collect()} == want and np.isfinite(model.eigen.mean).all()
    frame = model.release(bad)
    assert {tuple(r) for r in frame.rejected.collect()} == want and frame.df.count() == base.count() - 3


def test_merges_over_tasks_and_products_by_block(spark):
    x = np.random.default_rng(4).normal(size=(90, 7))
    df = spark.createDataFrame([(i, i % 11, v.tolist()) for i, v in enumerate(x)], "id long, part long, px array<double>").repartition(5)
    row = moments.merge_over_tasks(moments.partials(df, part="part"), 11, 3).collect()
    assert len(row) == 1 and np.allclose(moments.unpacked(row[0]).covariance(), np.cov(x.T))
    blocks = spectra._packed_blocks(df, "px", rows=8).persist()
    total = sum(np.square(np.frombuffer(bytes(r.p))).sum() * (1 if r.a == r.b else 2) for r in spectra.gram_blocks(blocks).collect())
    assert total == pytest.approx(np.square(x @ x.T).sum())
    blocks.unpersist()


def test_sweeps_train_side_by_side(spark):
    """The same models as one after the other, each setting by itself."""
    rng = np.random.default_rng(5)
    rows = [(i, f"p{i % 3}", "train" if i % 4 else "test", s, (rng.normal(size=6) * s + i % 3).tolist()) for i in range(120) for s in (0.1, 3.0)]
    df = spark.createDataFrame(rows, "id long, label string, split string, s double, pv array<double>")
    one = classify.rated_each(df, "s", hidden=(16,), max_iter=120, batch=10)
    far = classify.rated_each(df, "s", limit=10, hidden=(8,), max_iter=2)
    assert one.count() == 2 * 2 * 30 == far.count()
    rates = {(r.s, r.recogniser): r.f1 for r in measures.weighted_report(one, by=("s", "recogniser")).collect()}
    assert rates[0.1, "network"] > 0.95 and rates[0.1, "centroid"] > 0.95 and rates[3.0, "centroid"] < 0.9


def test_attack_fails_at_a_small_budget_on_scaled_pixels(spark):
    got = {r.eps: r for r in workloads.w9_attack(spark, "/root/testdata/sf0.001", budgets=(0.5, None), settings=((1, "scaled"),)).collect()}
    assert got[None].cosine > 0.9 and got[0.5].cosine < 0.3 and got[0.5].reid < got[None].reid
