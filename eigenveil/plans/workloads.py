"""The experiment workloads on the given tables (W1-W15); each returns a tidy table."""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sources
from ..functions import perturb
from ..operators import attack, baselines, classify, cohort, measures, moments, noise, project, scaling, spectra
from ..operators.release import PrivateEigenModel, PrivateEigenRelease
from ..params import ReleaseParams

KEY = "k1"
BUDGETS: tuple[float | None, ...] = (0.5, 1.0, 2.0, 3.0, 4.0, 5.0, 6.0, 7.0, 8.0, None)
#: Images per person in the experiments.
THRESHOLD = 100
#: Layers and epochs of the network where a workload trains many (the published ones: ``classify.HIDDEN``, ``classify.EPOCHS``).
LAYERS, EPOCHS = (256, 128), 60


def faces(spark: SparkSession, sf_dir: str, label: str = "lang", channels: int = 1, least: int = 0, part: str | None = None) -> DataFrame:
    """FX1 (or FX7): documents as images with a person; with ``least``, ``frequent`` ones, and with ``part`` those of the
    split's train or test, chosen before images are made."""
    docs = sources.table(spark, sf_dir, "documents")
    if part:
        docs = cohort.split(docs, id_="doc_id").where(F.col("split") == part).drop("split")
    if label in ("quality", "toxic"):
        docs = docs.join(sources.table(spark, sf_dir, "labels").select("doc_id", label), "doc_id")
    return sources.bigram_grid(frequent(docs, least, label) if least else docs, label, channels=channels)


def edge_model(images: DataFrame, nc: int = 47, eps: float | None = 8.0, **more) -> PrivateEigenModel:
    return PrivateEigenRelease(ReleaseParams(nc=nc, eps=eps, key=KEY, **more)).fit(images)


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def frequent(images: DataFrame, n: int = THRESHOLD, label: str = "label") -> DataFrame:
    """Persons with at least ``n`` images; all persons of a table in which none has so many."""
    names = images.groupBy(label).count().where((F.col("count") >= n) & F.col(label).isNotNull()).select(label)
    # at most one name for each n rows, so images need not be dealt out by it
    return images if names.isEmpty() else images.join(F.broadcast(names), label, "left_semi")


def _reports(released: DataFrame, by: str, hidden: tuple[int, ...] = LAYERS, max_iter: int = EPOCHS, kinds: tuple[str, ...] = ("network", "centroid"), **more) -> DataFrame:
    """Weighted report of each setting in ``by`` and recogniser, trained on released training rows."""
    rows = released if "split" in released.columns else cohort.split(released)
    # the report reads the predictions several times: they are kept, so that each network is trained once
    rated = classify.rated_each(rows, by, kinds, hidden=hidden, max_iter=max_iter, **more).persist()
    epochs = rated.groupBy(by, "recogniser").agg(F.max("epochs").alias("epochs"))
    report = measures.weighted_report(rated, by=(by, "recogniser"))
    same = [report[by].eqNullSafe(epochs[by]), report["recogniser"] == epochs["recogniser"]]
    done = sources_free(report.join(epochs, same).select(report["*"], epochs["epochs"]))
    rated.unpersist()
    return done


def eps_sweep(images: DataFrame, budgets=BUDGETS, nc: int = 47, hidden: tuple[int, ...] = LAYERS, max_iter: int = EPOCHS, **more) -> DataFrame:
    """The scores are made once; each budget only draws other noise.  One row for each budget and recogniser."""
    model = edge_model(images, nc, None, **more)
    scaled = model.scaled(images).persist()
    each = [scaled.select("id", "label", (F.col("scaled") if e is None else perturb("scaled", e, model.delta, KEY, "id")).alias("pv"), F.lit(e).cast("double").alias("eps")) for e in budgets]
    done = _reports(_union(each), "eps", hidden, max_iter)
    scaled.unpersist()
    return done


def sources_free(df: DataFrame) -> DataFrame:
    """A few rows of results, computed now."""
    return df.sparkSession.createDataFrame(df.toArrow())


def w1_dataset(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = cohort.keep_frequent(faces(spark, sf_dir), 100)
    return cohort.split(kept).groupBy("label", "split").agg(F.count("*").alias("n"))


def w2_gallery(spark: SparkSession, sf_dir: str) -> DataFrame:
    images = faces(spark, sf_dir)
    state = moments.moments(images)
    model = spectra.solve_direct(state, 8)
    total = float(np.trace(state.covariance()))
    rows = [(k, float(v), float(v) / total, x.tolist()) for k, (v, x) in enumerate(zip(model.values, model.vectors))]
    df = spark.createDataFrame(rows, "k int, eigval double, share double, vec array<double>")
    return df.select("k", "eigval", "share", project.as_image(F.col("vec"), 47, 62).alias("image"))


def w3_perturbed_gallery(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signal against noise of the released vectors at budgets 4 and 100."""
    images = faces(spark, sf_dir)
    model = edge_model(images, 47, None, allow_extreme=True)
    scaled = model.scaled(images)
    both = _union([scaled.select("id", F.lit(e).alias("eps"), "scaled", perturb("scaled", e, model.delta, KEY, "id").alias("pv")) for e in (4.0, 100.0)])
    power = lambda c: F.aggregate(c, F.lit(0.0), lambda s, x: s + x * x)
    return both.select("id", "eps", (power(F.col("scaled")) / power(F.zip_with("pv", "scaled", lambda x, y: x - y))).alias("snr"))


def w4_training_loss(spark: SparkSession, sf_dir: str, hidden: tuple[int, ...] = classify.HIDDEN, max_iter: int = classify.EPOCHS, until: tuple[float, int] | None = None) -> DataFrame:
    """The published layers, epochs and stopping rule, at budget 4; with ``until`` the epochs up to that tolerance and patience."""
    images = faces(spark, sf_dir, least=THRESHOLD)
    released = edge_model(images, 47, 4.0).release(images).df.where("label IS NOT NULL")
    train = cohort.split(released).where("split = 'train'").persist()
    net = classify.mlp_fit(train, hidden=hidden, max_iter=max_iter, until=until)
    train.unpersist()
    return spark.createDataFrame([(i + 1, float(x)) for i, x in enumerate(net.losses)], "epoch int, loss double")


def w5_eps_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return eps_sweep(faces(spark, sf_dir, least=THRESHOLD))


def w5_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planted classes, whose truth is known."""
    return _vector_sweep(sources.planted_faces(sources.table(spark, sf_dir, "embeddings")))


def _vector_sweep(images: DataFrame) -> DataFrame:
    """W5 on vectors, which are small enough to keep."""
    images = frequent(images).persist()
    done = eps_sweep(images, nc=32, irw=8, irh=8, enforce_cap=False)
    images.unpersist()
    return done


def w5_null_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels that the vectors do not show: the curve must stay at chance."""
    return _vector_sweep(sources.embedding_images(sources.table(spark, sf_dir, "embeddings")))


def w5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return eps_sweep(faces(spark, sf_dir, "quality", least=THRESHOLD))


def w5_source_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The source of a text as its person: no usable signal, so a second null control."""
    return eps_sweep(faces(spark, sf_dir, "source", least=THRESHOLD), budgets=(0.5, 8.0, None))


def w6_sheet(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight test rows at budget 4, as the network labels them."""
    images = faces(spark, sf_dir, least=THRESHOLD)
    released = edge_model(images, 47, 4.0).release(images).df.withColumn("eps", F.lit(4.0)).persist()
    done = sources_free(measures.sample_sheet(classify.rated_each(cohort.split(released), "eps", ("network",), hidden=LAYERS, max_iter=EPOCHS)))
    released.unpersist()
    return done


def w7_threshold_sweep(spark: SparkSession, sf_dir: str, steps: tuple[int, ...] = (20, 40, 60, 80, 100, 200), nc: int = 128) -> DataFrame:
    """More images per person, at budget 8: the test rows stay the same."""
    images = faces(spark, sf_dir)
    released = cohort.split(edge_model(images, nc, 8.0, enforce_cap=False).release(images).df).persist()
    test, train = released.where("split = 'test'"), released.where("split = 'train'")
    each = [cohort.cap_per_class(train, n).unionByName(test).withColumn("imthresh", F.lit(n)) for n in steps]
    done = sources_free(_reports(_union(each), "imthresh"))
    released.unpersist()
    return done


def w8_nc_sweep(spark: SparkSession, sf_dir: str, steps: tuple[int, ...] = (5, 10, 20, 30, 40, 47, 64, 100, 128)) -> DataFrame:
    """Component counts at threshold 100, with the budget held per index and per record."""
    images = faces(spark, sf_dir, least=THRESHOLD)
    model = edge_model(images, max(steps), None, enforce_cap=False)
    scaled = model.scaled(images).persist()
    each = []
    for nc in steps:
        for mode in ("index", "l1"):
            pv = perturb(F.slice("scaled", 1, nc), 8.0, noise.sensitivity(nc, mode), KEY, "id")
            each.append(scaled.select("id", "label", pv.alias("pv"), F.lit(f"{nc} {mode}").alias("setting")))
    made = _reports(_union(each), "setting")
    done = sources_free(made.select(F.split("setting", " ")[0].cast("int").alias("nc"), F.split("setting", " ")[1].alias("mode"), *[c for c in made.columns if c != "setting"]))
    scaled.unpersist()
    return done


def chosen_components(spark: SparkSession, sf_dir: str, tol: float = 0.01) -> DataFrame:
    """M16a on the curve of W8: for each recogniser and way of holding the budget, the count after which F1 gains under ``tol``."""
    curves: dict[tuple[str, str], list[tuple[int, float]]] = {}
    for r in w8_nc_sweep(spark, sf_dir).collect():
        curves.setdefault((r["recogniser"], r["mode"]), []).append((r["nc"], r["f1"]))
    return spark.createDataFrame([(k, m, spectra.choose_nc(c, tol)) for (k, m), c in sorted(curves.items())], "recogniser string, mode string, nc int")


def _guesses(spark: SparkSession, sf_dir: str, domain: str, channels: int, noise_on: str, components: int, n: int, targets: int | None = None):
    """(tested, values, guesses, attacker): images of test rows, their values, and ``guesses(*budgets)``, the reconstructions
    of what is released of them at each budget, with the truth.

    ``noise_on`` is "scaled" (the release: noise on values in [0, 1], scaled back by the
    attacker) or "raw" (noise of the same scale on centred values that were not scaled).
    """
    images = faces(spark, sf_dir, channels=channels)
    many = images.select(F.size("px")).first()
    if many and many[0] > spectra.DIRECT_LIMIT:  # a fit of these reads them again and again
        images = images.persist()
    model = edge_model(images, 47, None, domain=domain, enforce_cap=False)
    attacker = attack.fit_attacker(images, components, n) if domain == "pixel" else model.eigen
    images.unpersist()
    tested = faces(spark, sf_dir, channels=channels, part="test")
    tested = tested.orderBy("id").limit(targets) if targets else tested
    truth = tested.withColumn("truth", F.col("px"))
    if noise_on == "scaled":
        values = model.scaled(truth).withColumnRenamed("scaled", "v")
    else:
        values = project.centred(truth, model.eigen.mean, out="v")
    values = values.persist() if targets else values

    def guesses(*budgets: float | None) -> DataFrame:
        each = [values.withColumn("pv", F.col("v") if e is None else perturb("v", e, model.delta if noise_on == "scaled" else 1.0, KEY, "id")).withColumn("eps", F.lit(e).cast("double")) for e in budgets]
        guessed = attack.reconstruct(_union(each).drop("v"), attacker, add_mean=True, domain=domain, edge=model if noise_on == "scaled" else None)
        return measures.reconstruction(guessed.withColumn("px", F.col("truth").cast("array<double>")))

    return tested, values, guesses, attacker


def w9_attack(spark: SparkSession, sf_dir: str, budgets=(0.5, 4.0, 8.0, None), domain: str = "pixel", settings=((1, "scaled"), (1, "raw"), (3, "scaled")), components: int = 2000, n: int = 1000) -> DataFrame:
    """Reconstruction from released vectors of test rows, judged by error, cosine and re-identification.

    The attacker has the eigenvectors of 1,000 images and their flips (as many as these
    give, 2,000 at most), grey and in three channels.
    """
    out, marks = [], ("mse", "psnr", "cosine")
    with sources.small_batches(spark):
        for channels, noise_on in settings:
            tested, _, guesses, attacker = _guesses(spark, sf_dir, domain, channels, noise_on, components, n)
            # guesses are combinations of the attacker's eigenvectors: few coordinates hold all distances to them
            gallery = attack.packed(attack.coordinates(tested.select("id", "px"), attacker, "px"), "v").persist()
            for eps in budgets:
                rated = attack.packed(attack.coordinates(guesses(eps).select("id", "guess", *marks), attacker, "guess"), "v", marks).persist()
                found = attack.nearest_of(rated, gallery, marks).withColumnRenamed("rate", "reid")
                out.append(found.select(F.lit(channels).alias("channels"), F.lit(noise_on).alias("noise_on"), F.lit(eps).cast("double").alias("eps"), *marks, "reid"))
                rated.unpersist()
            gallery.unpersist()
    return _union(out)


def w9_targets(spark: SparkSession, sf_dir: str, budgets=(0.5, 1.0, 2.0, 4.0, 8.0, None)) -> DataFrame:
    """The attack's table of two targets: error, peak ratio and cosine of each at each budget, in three channels."""
    _, values, guesses, _ = _guesses(spark, sf_dir, "pixel", 3, "scaled", 2000, 1000, targets=2)
    done = sources_free(guesses(*budgets).select("id", "eps", "mse", "psnr", "cosine"))
    values.unpersist()
    return done


def w9_score_attack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w9_attack(spark, sf_dir, domain="score", settings=((1, "scaled"),))


def w10_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Published marks and seconds beside measured ones: every test row against a gallery of the published size.

    Encrypted matches: operation counts, seconds of one probe in one process, and how often
    the nearest row has the probe's person.  Private: seconds of release and recognition.
    """
    base = cohort.split(sources.planted_faces(sources.table(spark, sf_dir, "embeddings"))).persist()
    gallery, probes = base.where("split = 'train'").orderBy("id").limit(798), base.where("split = 'test'")
    model = spectra.fit(base.where("split = 'train'"), 4)
    persons = gallery.select(F.col("id").alias("match"), F.col("label").alias("found"))
    counts = []
    for name, variant in (("H1", "interactive"), ("H2", "packed")):
        got = baselines.encrypted_match(probes, gallery, model, variant).join(probes.select("id", "label"), "id").join(F.broadcast(persons), "match")
        means = [F.avg(c).alias(c) for c in ("exponentiations", "decryptions", "rounds", "seconds")]
        counts.append(got.agg(*means, F.avg((F.col("label") == F.col("found")).cast("int")).alias("right")).withColumn("approach", F.lit(name)))
    edge = edge_model(base, 4, 8.0, irw=8, irh=8, enforce_cap=False)
    released = cohort.split(edge.release(base).df).persist()
    net = classify.centroid_fit(released.where("split = 'train'"))
    rated = classify.predict(released.where("split = 'test'"), net).agg(F.avg((F.col("label") == F.col("pred")).cast("int")).alias("right"))
    total = measures.per_image_time(base.count(), lambda: edge.release(base).df, lambda: classify.predict(released, net))["total"]
    private = rated.select(*[F.lit(0.0).alias(c) for c in ("exponentiations", "decryptions", "rounds")], F.lit(total).alias("seconds"), "right", F.lit("private").alias("approach"))
    marks = measures.issue_matrix(spark).join(measures.baseline_times(spark), "approach", "left")
    done = sources_free(marks.join(F.broadcast(sources_free(_union([*counts, private]))), "approach", "left"))
    released.unpersist()
    base.unpersist()
    return done


def w11_time_per_image(spark: SparkSession, sf_dir: str, steps: tuple[int, ...] = (10, 47, 90, 128), hidden: tuple[int, ...] = classify.HIDDEN) -> DataFrame:
    """Seconds per image of the release and of the published network, and of one image through it alone.

    t_rand, t_rec and total are wall time over all cores by the number of images; t_one is
    the time of a single image through the network in one process, the measure published.
    Weights don't change what a product costs, so a few steps of training suffice here.
    """
    images = faces(spark, sf_dir).persist()
    n = images.count()
    full = edge_model(images, max(steps), 8.0, enforce_cap=False)
    out = []
    for nc in steps:
        p = full.settings
        model = PrivateEigenModel(type(p)(**{**p.__dict__, "nc": nc}), full.eigen.take(nc), scaling.Bounds(full.bounds.scope, full.bounds.lo[:nc], full.bounds.hi[:nc]))
        released = model.release(images).df.persist()
        few = released.where("label IS NOT NULL").orderBy("id").limit(500)
        net = classify.mlp_fit(few, hidden=hidden, max_iter=1)
        one = np.array(released.first()["pv"])[None]
        net.probabilities(one)
        began = time.perf_counter()
        for _ in range(20):
            net.probabilities(one)
        alone = (time.perf_counter() - began) / 20
        got = measures.per_image_time(n, lambda m=model: m.release(images).df, lambda r=released, t=net: classify.predict(r, t))
        out.append((nc, *map(float, got.values()), alone))
        released.unpersist()
    images.unpersist()
    return spark.createDataFrame(out, "nc int, t_rand double, t_rec double, total double, t_one double")


def cost_growth_nc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Q6: least-squares line of the release's seconds per image over the number of components."""
    curve = w11_time_per_image(spark, sf_dir, steps=(16, 48, 96, 128), hidden=(64,))
    return measures.fit_slope(curve, "nc", "t_rand")


def cost_growth_n(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = (0.25, 0.5, 0.75, 1.0)) -> DataFrame:
    """Q7: seconds per image of recognition by networks trained on more and more rows, and the line over their number."""
    images = faces(spark, sf_dir)
    released = cohort.split(edge_model(images, 47, 8.0).release(images).df.where("label IS NOT NULL")).persist()
    train, n = released.where("split = 'train'"), released.count()
    out = []
    for share in shares:
        mine = cohort.split(train.drop("split"), share, salt="grow").where("split = 'train'")
        net = classify.mlp_fit(mine, hidden=LAYERS, max_iter=3)
        out.append((mine.count(), float(share), measures.seconds(lambda t=net: classify.predict(released, t)) / n))
    released.unpersist()
    curve = spark.createDataFrame(out, "n_train long, share double, t_rec double")
    return curve.crossJoin(F.broadcast(sources_free(measures.fit_slope(curve, "n_train", "t_rec"))))


def baseline_accuracy(spark: SparkSession, sf_dir: str, eps: float = 8.0) -> DataFrame:
    """B1-B4 and B12 beside the release: raw pixels, clean scores, eigenfaces of one process, the most frequent person."""
    images = faces(spark, sf_dir, least=THRESHOLD).persist()
    model = edge_model(images, 47, eps)
    train = cohort.split(images).where("split = 'train'")
    local = spectra.fit_one_task(train, model.eigen.nc)
    each = {
        "private": model.release(images).df,
        "no_privacy": model.release(images, eps=None).df,
        "raw_pixels": baselines.raw_pixels(images).select("id", "label", "pv"),
        "clean_scores": baselines.clean_scores(model, images).select("id", "label", "pv"),
        "one_process": project.scores(images, local).select("id", "label", F.col("score").alias("pv")),
    }
    made = _union([df.select("id", "label", "pv", F.lit(name).alias("baseline")) for name, df in each.items()])
    report = _reports(made, "baseline", kinds=("centroid",))
    parts = cohort.split(images.where("label IS NOT NULL").select("id", "label")).where("split = 'test'")
    common = measures.weighted_report(classify.majority(parts)).withColumn("baseline", F.lit("majority")).withColumn("recogniser", F.lit("none")).withColumn("epochs", F.lit(0).cast("long"))
    done = sources_free(report.unionByName(common))
    images.unpersist()
    return done


def w12_partitions(spark: SparkSession, sf_dir: str, counts: tuple[int, ...] = (1, 2, 4, 8, 16)) -> DataFrame:
    """Merged against pooled covariance for several numbers of parts of uneven sizes, one of them of one row."""
    out = []
    fixtures = {"vectors": sources.embedding_images(sources.table(spark, sf_dir, "embeddings")), "fact_grid": sources.fact_grid(sources.table(spark, sf_dir, "lineitem")).select("id", "px")}
    for name, made in fixtures.items():
        base = made.persist()  # each count of parts reads it again
        pooled = moments.covariance_two_round(base)
        least = base.agg(F.min("id")).first()[0]
        for parts in counts:
            began = time.perf_counter()
            # part 0 takes half of the rows, the last part the first row alone
            half = F.greatest(F.lit(0), F.pmod("id", F.lit(2 * parts)) - parts)
            placed = base.withColumn("part", F.when(F.col("id") == least, parts).otherwise(half))
            # rows of a part together: a task holds the states of wide rows one at a time
            placed = placed.repartition(parts + 1, "part").sortWithinPartitions("part")
            state = moments.unpacked(moments.merge_over_tasks(moments.partials(placed, part="part"), parts + 1).collect()[0])
            out.append((name, parts + 1, moments_error(state.covariance(), pooled), time.perf_counter() - began))
            del state
        base.unpersist()
    return spark.createDataFrame(out, "fixture string, parts int, max_abs_err double, sec double")


def moments_error(a: np.ndarray, b: np.ndarray) -> float:
    return measures.merge_error(a, b)


def w13_timing_context(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.baseline_times(spark)


def w14_capture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Released captures of a replayed stream, on fixed axes: equal to the batch release row for row."""
    from .. import streaming

    base = sources.embedding_images(sources.table(spark, sf_dir, "embeddings"))
    eigen = spectra.EigenModel(np.zeros(64), np.ones(16), project.sign_axes(16), 0, 8, 8, 1)
    params = ReleaseParams(nc=16, eps=8.0, key=KEY, irw=8, irh=8, enforce_cap=False)
    model = PrivateEigenModel(params, eigen, scaling.fit_bounds(project.scores(base, eigen)))
    folder = f"{sources.shared_folder(spark)}/captures-{time.time_ns()}"
    streaming.write_captures(base, f"{folder}/in", 3)
    streaming.run_to_end(streaming.perturbed(streaming.once_each(streaming.capture(spark, f"{folder}/in")), model), f"{folder}/out", f"{folder}/log")
    released = spark.read.parquet(f"{folder}/out").select("id", F.posexplode("pv").alias("idx", "v"))
    return released.select("id", F.col("idx").cast("long").alias("idx"), (F.round("v", 6) + 0.0).alias("value"))


def w15_sensitivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    images = faces(spark, sf_dir, least=THRESHOLD)
    model = edge_model(images, 47, None)
    scaled = model.scaled(images).persist()
    deltas = {mode: noise.sensitivity(model.width, mode) for mode in ("index", "euclidean", "l1")}
    each = [scaled.select("id", "label", perturb("scaled", 8.0, d, KEY, "id").alias("pv"), F.lit(m).alias("mode")) for m, d in deltas.items()]
    delta = F.element_at(F.create_map(*[x for m, d in deltas.items() for x in (F.lit(m), F.lit(float(d)))]), F.col("mode"))
    done = sources_free(_reports(_union(each), "mode").withColumn("eps_index", 8.0 / delta).withColumn("eps_record", model.width * 8.0 / delta))
    scaled.unpersist()
    return done


WORKLOADS = {f.__name__: f for f in (w1_dataset, w2_gallery, w3_perturbed_gallery, w4_training_loss, w5_eps_sweep, w5_planted, w5_null_control, w5_quality, w5_source_control, w6_sheet, w7_threshold_sweep, w8_nc_sweep, chosen_components, w9_attack, w9_score_attack, w9_targets, w10_comparison, w11_time_per_image, cost_growth_nc, cost_growth_n, baseline_accuracy, w12_partitions, w14_capture, w15_sensitivity)}
