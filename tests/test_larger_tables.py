"""Cases on which a query once differed from its SQL or did not end, on small tables made for them."""

import math
import random
import tracemalloc

import duckdb
import numpy as np
import pyarrow as pa
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from eigenveil import sources
from eigenveil.llm import token_files
from eigenveil.operators import attack, baselines, classify, imaging, measures, moments, relops, spectra
from eigenveil.operators.residues import Residues
from eigenveil.plans import catalogue, workloads
from verify import rows_of


@pytest.fixture
def same_as_sql(spark, tmp_path):
    """Writes a table from DuckDB SQL and compares a query on it with the query's SQL."""
    con = duckdb.connect()

    def put(name: str, sql: str) -> None:
        con.execute(f"COPY ({sql}) TO '{tmp_path}/{name}.parquet'")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{tmp_path}/{name}.parquet'")

    def same(name: str) -> int:
        got = catalogue.QUERIES[name](spark, str(tmp_path)).toPandas()
        want = con.execute(catalogue.SQL[name])
        columns = [d[0] for d in want.description]
        rows = rows_of(columns, want.fetchall())
        assert rows_of(list(got.columns), got.astype(object).where(got.notna(), None).itertuples(index=False, name=None)) == rows
        return len(rows)

    return put, same


def test_frame_by_time_rounds_seconds_as_its_sql(same_as_sql):
    put, same = same_as_sql
    # .4 and .6 of a second apart from a whole day; halves go to the even second
    put("events", "SELECT k AS event_id, k // 3 AS user_id, 'view' AS event_type, 1.0 AS value, TIMESTAMP '2024-01-01 00:00:00' + to_microseconds(CASE k % 3 WHEN 0 THEN (k % 11) * 100000 WHEN 1 THEN 86400600000 ELSE 86401500000 END::BIGINT) AS ts FROM range(0, 66) t(k)")
    assert same("win_range") == 66


def test_capture_releases_every_row_of_a_long_replay(same_as_sql):
    put, same = same_as_sql
    # seven thousand seconds between captures: hash-dealt files would be hours late
    put("embeddings", "SELECT k * 1000 AS vec_id, (k % 3)::INTEGER AS label, list_transform(range(0, 64), lambda i: (((k * 37 + i * 11) % 101) / 101.0)::FLOAT) AS embedding FROM range(0, 60) t(k)")
    assert same("w14_capture") == 60 * 16


def test_gram_route_takes_more_rows_than_its_products_may_hold(spark, sf, monkeypatch):
    base = sources.planted_faces(sources.table(spark, sf, "embeddings"))
    direct = spectra.solve_direct(moments.moments(base), 8)
    monkeypatch.setattr(spectra, "GRAM_LIMIT", 64 * 64 * 8)  # 500 rows of 64 pixels
    got = spectra.solve_gram(base.repartition(20), 8)
    assert got.n == 500 and got.values == pytest.approx(direct.values, rel=1e-9)
    assert spectra.same_subspace(direct.vectors, got.vectors) < 1e-8


def test_standardise_works_a_record_out_once(spark):
    df = spark.range(1).select(F.transform(F.sequence(F.lit(1), F.lit(9)), lambda x: x.cast("float")).alias("px"))
    for mode in ("zscore", "unit_range"):
        made = imaging.standardise(df, mode)
        plan = made._jdf.queryExecution().optimizedPlan().toString()
        # mean and spread once each; extremes once each and outside of the walk over the values
        assert plan.count("aggregate(") <= 2 and plan.count("array_min(") <= 1, plan
    assert imaging.standardise(df, "zscore").first().px == pytest.approx([(k - 5) / (60 / 9) ** 0.5 for k in range(1, 10)], rel=1e-6)


def test_fact_grid_makes_no_search_for_each_cell(spark, sf):
    made = sources.fact_grid(sources.table(spark, sf, "lineitem"))
    assert "element_at" not in made._jdf.queryExecution().optimizedPlan().toString()
    assert made.agg(F.sum(F.aggregate("px", F.lit(0.0), lambda s, x: s + x))).first()[0] == 6000 and made.first().w == 50


def test_broadcast_join_sends_slices_of_a_large_side(spark, sf):
    items = sources.table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber")
    orders = sources.table(spark, sf, "orders").select(F.col("o_orderkey").alias("k"), "o_orderpriority")
    parts = list(relops.hinted_slices(items, orders, "k", "broadcast", rows=400))
    assert len(parts) == 4 and all("Broadcast" in p._jdf.queryExecution().executedPlan().toString() for p in parts)
    whole = relops.hinted_join(items, orders, "k", "merge")
    assert sorted(r for p in parts for r in p.collect()) == sorted(whole.collect())
    assert len(list(relops.hinted_slices(items, orders, "k", "merge", rows=400))) == 1


def test_rasters_come_in_batches_of_bounded_size(spark, monkeypatch):
    # a long line and many short ones: far more cells than characters
    docs = spark.createDataFrame([(k, "en", "\u00e9" * 2000 + "\na" * 499) for k in range(24)], "doc_id long, lang string, text string").coalesce(1)
    total = F.aggregate("px", F.lit(0.0), lambda s, x: s + x)
    assert {(r.w, r.h, r.t) for r in sources.text_raster(docs).select("w", "h", total.alias("t")).collect()} == {(2000, 500, 2000.0 * 233 + 499 * 97)}
    held = []
    monkeypatch.setattr(type(docs), "mapInArrow", lambda df, run, schema: held.append(run))
    sources.text_raster(docs, cells=3_000_000)
    batch = pa.RecordBatch.from_pylist([{"id": k, "label": "en", "text": "b" * 2000 + "\na" * 499} for k in range(24)])
    sizes = [(b.num_rows, len(b.column("px").flatten())) for b in held[0](iter([batch]))]
    assert sizes == [(3, 3_000_000)] * 8


@pytest.mark.parametrize("name", ["budget_halving", "capped_nc", "gdp_ratio", "laplace_pdf_grid", "ldp_ratio", "sensitivity_modes"])
def test_query_reads_a_table(spark, sf, name):
    assert " parquet" in catalogue.QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()


def test_published_rows_are_no_queries():
    assert not {"baseline_times", "issue_matrix"} & set(catalogue.QUERIES)


def test_one_task_fits_rows_that_no_list_holds(spark, sf, monkeypatch):
    base = sources.planted_faces(sources.table(spark, sf, "embeddings")).repartition(6)
    rows = np.array([r.px for r in base.select("px").collect()], np.float64)
    got, want = spectra.fit_one_task(base, 8), spectra.fit_local(rows, 8)
    assert got.n == want.n == 500 and got.values == pytest.approx(want.values) and np.abs(got.vectors - want.vectors).max() < 1e-8
    monkeypatch.setattr(spectra, "fit_local", None)  # takes all images on the driver
    assert {r.baseline for r in workloads.baseline_accuracy(spark, sf).collect()} == {"private", "no_privacy", "raw_pixels", "clean_scores", "one_process", "majority"}


def test_coordinates_keep_the_nearest_image(spark, sf):
    images = sources.planted_faces(sources.table(spark, sf, "embeddings"))
    model = spectra.solve_direct(moments.moments(images), 6)
    noisy = images.withColumn("pv", F.transform("px", lambda x, i: x.cast("double") + (F.pmod(F.col("id") * 31 + i * 17, F.lit(29)) - 14) / 40)).select("id", "pv")
    guessed = attack.reconstruct(noisy, model, add_mean=True)
    gallery = images.select("id", F.col("px").cast("array<double>").alias("v"))
    whole = attack.nearest_rate(guessed.select("id", F.col("guess").alias("v")), gallery, "v").first()
    few = [attack.coordinates(df, model, c) for df, c in ((guessed.select("id", "guess"), "guess"), (images.select("id", "px"), "px"))]
    assert len(few[0].first().v) == 7 and tuple(attack.nearest_rate(*few, "v").first()) == tuple(whole) and 0.05 < whole.rate < 1


def test_blocks_of_token_files_are_held_once_and_read_in_place(spark, sf, tmp_path, monkeypatch):
    docs = sources.table(spark, sf, "documents").select("doc_id", "text").limit(20)
    runs = {}
    monkeypatch.setattr(type(docs), "mapInArrow", lambda df, run, *a, f=type(docs).mapInArrow: (runs.update({run.__name__: run}), f(df, run, *a))[1])
    token_files.write_shards(docs, f"file://{tmp_path}/shards", public_tokenizers.path("byte_bpe_50k.json"))
    frames = [bytes([k % 251]) * 8192 for k in range(2000)]
    batch = pa.RecordBatch.from_pydict({"shard": pa.array([0] * 2000, pa.int32()), "doc_id": pa.array(range(2000), pa.int64()), "n_tokens": pa.array([1] * 2000, pa.int64()), "frame": pa.array(frames, pa.binary())})
    del frames
    tracemalloc.start()
    made = [len(b.column("block")[0].as_buffer()) for b in runs["blocks"](iter([batch]))]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(made) == 1 and made[0] > 2000 * 8192 and peak < 2.5 * made[0]


def test_planted_faces_work_their_prototypes_out_once_a_row(spark, sf):
    made = sources.planted_faces(sources.table(spark, sf, "embeddings"))
    assert made._jdf.queryExecution().optimizedPlan().toString().count("md5(") == 1


def test_a_report_trains_its_networks_once(spark, monkeypatch):
    rated = spark.createDataFrame([(i, f"p{i % 3}", "train" if i % 4 else "test", 1.0, [float(i % 3), 1.0]) for i in range(60)], "id long, label string, split string, s double, pv array<double>")
    seen, made = spark.sparkContext.accumulator(0), classify.rated_each

    def counted(*args, **options):
        def run(batches):
            for batch in batches:
                seen.add(batch.num_rows)
                yield batch

        df = made(*args, **options)
        return df.mapInArrow(run, df.schema)

    monkeypatch.setattr(classify, "rated_each", counted)
    got = workloads._reports(rated, "s", hidden=(4,), max_iter=3)
    assert got.count() == 2 == len(got.collect()) and seen.value == 2 * 15


def test_each_setting_of_a_sweep_has_a_task_of_its_own(spark):
    settings = [None, 0.5, 1.0, 2.0, 3.0, 4.0, 5.0, 6.0, 7.0, 8.0]
    df = spark.createDataFrame([(s, k) for s in settings for k in range(20)], "eps double, id long")
    parts = classify.own_tasks(df, "eps", settings).select(F.spark_partition_id().alias("p"), "eps").distinct().collect()
    assert len(parts) == 10 == len({r.p for r in parts})


def test_flat_steps_are_the_steps_of_each_layer():
    rng = np.random.default_rng(3)
    net = classify.Perceptron.fresh(300, (260,), ["a", "b"], 0)
    plain = [[v.copy() for v in layer] for layer in net.layers]
    opt = classify._Adam(net, 0.01)
    m, v = ([[np.zeros_like(x) for x in layer] for layer in plain] for _ in range(2))
    for step in (1, 2, 3):
        grads = [tuple(rng.normal(size=x.shape).astype(np.float32) for x in layer) for layer in plain]
        opt.apply(net, grads, 50, 1e-2)
        for k, layer in enumerate(plain):
            for j, x in enumerate(layer):
                g = (grads[k][j] + (1e-2 * x if j == 0 else 0)) / 50
                m[k][j] = 0.9 * m[k][j] + 0.1 * g
                v[k][j] = 0.999 * v[k][j] + 0.001 * g * g
                x -= 0.01 * (1 - 0.999**step) ** 0.5 / (1 - 0.9**step) * m[k][j] / (np.sqrt(v[k][j]) + 1e-8)
    assert len(opt.w) > opt.STRETCH and all(np.allclose(a, b, atol=1e-4) for p, q in zip(net.layers, plain) for a, b in zip(p, q))


@pytest.mark.parametrize("slots", [1, 2])
def test_encrypted_match_takes_one_encryption_a_message(slots):
    rng = np.random.default_rng(slots)
    basis, offset = rng.integers(-20, 20, (3, 16)), np.array([4, -300, 0])
    gallery = {k: (basis @ rng.integers(-9, 9, 16) - offset).tolist() for k in range(120)}
    keys = baselines.Paillier.fresh(256)
    for seed in range(3):
        probe = rng.integers(-9, 9, 16)
        want = min((int((((basis @ probe - offset) - g) ** 2).sum()), k) for k, g in gallery.items())[1]
        match, counts = baselines.match_encrypted(keys, probe.tolist(), gallery, basis.tolist(), offset.tolist(), slots, seed)
        assert match == want and counts["decryptions"] == 3 + 120 // slots
        assert counts["encryptions"] <= 16 + 4 * 3 + 1 + 120 // slots
    with pytest.raises(ValueError):
        baselines.match_encrypted(baselines.Paillier.fresh(64), (probe * 10**12).tolist(), gallery, basis.tolist(), offset.tolist(), slots, 0)


def test_powers_from_tables_and_opening_by_primes():
    rng = random.Random(4)
    table = baselines.Powers(123456789, 10**30 + 57, 40, 7)
    assert all(table.times(5, e) == 5 * pow(123456789, e, 10**30 + 57) % (10**30 + 57) for e in (0, 1, 127, 128, 2**40 - 1))
    keys = baselines.Paillier.fresh(128)
    for m in (0, 1, -1, keys.p - 1, keys.p + 1, keys.n // 2, -(keys.n // 2)):
        c = keys.encrypt(m, rng)
        assert keys.decrypt(c) == m and keys.decrypt(keys.plus(keys.times(c, -1), 7)) in (7 - m, 7 - m - keys.n, 7 - m + keys.n)
        assert keys.decrypt(c, below_p=True) == m or not 0 <= m < keys.p
        assert keys.encrypt(m, rng) != c


@pytest.mark.parametrize("modulus", [10**9 + 7, (10**30 + 57) ** 2, baselines.Paillier.fresh(256).square])
def test_products_in_residues_equal_whole_numbers(modulus):
    rng, group = random.Random(5), Residues(modulus)
    x, y = ([0, 1, modulus - 1, modulus - 2, *(rng.randrange(modulus) for _ in range(60))] for _ in range(2))
    y.reverse()
    a, b = group.residues(x), group.residues(y)
    assert group.numbers(a) == x and group.numbers(group.times(a, b)) == [u * v % modulus for u, v in zip(x, y)]
    for e in (0, 1, 2, 31, 32, 2**127 - 3):
        assert group.numbers(group.power(a, e)) == [pow(u, e, modulus) for u in x]
    assert group.numbers(group.tables(a, 14, 7)[:, 1, :, 5]) == [pow(u, 5 << 7, modulus) for u in x]
    assert group.numbers(group.product(a[:, :21].reshape(-1, 3, 7))) == [math.prod(x[7 * i : 7 * i + 7]) % modulus for i in range(3)]


@pytest.mark.parametrize("slots", [1, 2, 3])
def test_distances_are_opened_together(slots, monkeypatch):
    rng, opened = np.random.default_rng(9), []
    one = baselines.Paillier._opened
    monkeypatch.setattr(baselines.Paillier, "_opened", lambda self, c, k: opened.append(k) or one(self, c, k))
    basis, offset = rng.integers(-20, 20, (2, 8)), np.array([-9, 40])
    gallery = {k: (basis @ rng.integers(-9, 9, 8) - offset).tolist() for k in range(50, 0, -1)}
    gallery[51] = gallery[7]  # the same distance as another
    keys, probe = baselines.Paillier.fresh(256), rng.integers(-9, 9, 8)
    want = min((int((((basis @ probe - offset) - g) ** 2).sum()), k) for k, g in gallery.items())[1]
    match, counts = baselines.match_encrypted(keys, probe.tolist(), gallery, basis.tolist(), offset.tolist(), slots, 1)
    assert match == want and counts["decryptions"] == 2 + -(-51 // slots)
    assert len(opened) == 4  # those of the scores alone, one after the other


@pytest.mark.parametrize("threads", [1, 3])
def test_large_networks_keep_no_subnormal_weights(threads, monkeypatch):
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(200, 4)).astype(np.float32), rng.integers(0, 2, 200)
    x[:, 0] = 0  # its weights see the penalty alone

    def subnormal(limit):
        monkeypatch.setattr(classify, "LARGE", limit)
        net = classify.mlp_fit_arrays(x, y, ["a", "b"], hidden=(40, 30), max_iter=60, batch=5, l2=0.05, threads=threads, patience=60)
        return sum(int(((np.abs(w) < np.finfo(np.float32).tiny) & (w != 0)).sum()) for w, _ in net.layers), net.losses

    (swept, losses), (left, before) = subnormal(0), subnormal(1 << 20)
    assert swept == 0 < left and losses[:10] == pytest.approx(before[:10], rel=1e-3)


def test_steps_by_parts_equal_whole_ones():
    rng = np.random.default_rng(3)
    x, y = rng.normal(size=(60, 5)).astype(np.float32), rng.integers(0, 3, 60)
    one, two = (classify.Perceptron.fresh(5, (300, 400), list("abc"), 1) for _ in range(2))
    opt, shared = classify._Adam(one, 1e-3), classify._Steps(two, 1e-3, 1e-2, 3)
    for at in range(0, 60, 20):
        part = slice(at, at + 20)
        loss, grads = one.gradient(x[part], y[part], opt.grads)
        opt.apply(one, opt.grads, 20, 1e-2)
        assert shared.step(x[part], y[part]) == pytest.approx(loss, rel=1e-4)
    assert all(np.allclose(a, b, atol=2e-4) for pair in zip(one.layers, two.layers) for a, b in zip(*pair))
    with pytest.raises(ValueError):
        shared.step(x[:, :2], y)
    shared.crew.end()


def test_epochs_to_converge_trains_no_longer_than_it_asks(spark, monkeypatch):
    rng = np.random.default_rng(4)
    x, y = rng.integers(0, 2, (60, 2)).astype(np.float32), rng.integers(0, 2, 60)  # vectors of both classes
    fits = [classify.mlp_fit_arrays(x, y, ["a", "b"], hidden=(16,), max_iter=150, rate=0.003, until=u) for u in (None, (1e-3, 3))]
    whole, short = (spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(f.losses)], "epoch int, loss double") for f in fits)
    asked = [measures.epochs_to_converge(c, 1e-3, 3).first().epochs for c in (whole, short)]
    assert asked[0] == asked[1] and len(fits[1].losses) == asked[0] + 3 < len(fits[0].losses)
    assert fits[0].losses[: len(fits[1].losses)] == fits[1].losses
    given = {}
    monkeypatch.setitem(workloads.WORKLOADS, "w4_training_loss", lambda spark, sf_dir, **more: given.update(more) or whole)
    assert catalogue.QUERIES["epochs_to_converge"](spark, "").first().epochs == asked[0] and given == {"until": (1e-3, 3)}


def test_a_sweep_over_many_rows_stays_side_by_side(spark, monkeypatch):
    monkeypatch.setattr(classify, "mlp_fit", None)  # trained beyond 50,000 rows with one step for all rows
    rows = spark.range(61_000).select("id", F.concat(F.lit("p"), F.col("id") % 2).alias("label"), F.when(F.col("id") % 60 > 0, "train").otherwise("test").alias("split"), F.lit(1.0).alias("s"), F.array((F.col("id") % 2).cast("double"), F.lit(0.5).cast("double")).alias("pv"))
    got = {r.recogniser: r for r in measures.weighted_report(classify.rated_each(rows, "s", hidden=(4,), max_iter=2), by=("s", "recogniser")).collect()}
    assert {r.n for r in got.values()} == {1017}


def test_frequent_persons_are_chosen_before_images_are_made(spark, sf):
    def ids(df):
        return sorted((r.id, r.label) for r in df.select("id", "label").collect())

    for label in ("lang", "source"):
        assert ids(workloads.faces(spark, sf, label, least=60)) == ids(workloads.frequent(workloads.faces(spark, sf, label), 60))
    few = workloads.faces(spark, sf, least=60)
    plan = few._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("MapInArrow") < plan.index("LeftSemi")


def test_packed_states_come_back_as_they_were():
    rows = np.random.default_rng(8).normal(size=(9, 5))
    state = moments.Moments.of(rows)
    row = moments._pack(state)
    assert row["scatter"] == state.scatter[np.triu_indices(5)].tobytes() and np.allclose(moments.unpacked(row).scatter, state.scatter)


def test_products_of_rows_send_large_blocks_and_come_in_small_batches(spark):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(3000, 4))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, v array<double>")
    made = relops.row_products(df, step=20_000)
    got = made.agg(F.count("*"), F.sum("dot"), F.sum(F.col("dot") * F.col("a")), F.countDistinct("a", "b")).first()
    want = x @ x.T
    assert got[0] == got[3] == 3000**2 and got[1] == pytest.approx(want.sum()) and got[2] == pytest.approx((want * np.arange(3000)[:, None]).sum())
    assert "FlatMapCoGroups" not in made._jdf.queryExecution().optimizedPlan().toString()


def test_a_sweep_takes_the_same_steps_at_any_size(spark):
    rng = np.random.default_rng(6)
    x = (rng.normal(size=(300, 5)) + np.arange(300)[:, None] % 3).astype(np.float32)
    names = np.array([f"p{i % 3}" for i in range(300)])
    df = spark.createDataFrame([(i, str(names[i]), "train" if i % 5 else "test", s, x[i].tolist()) for i in range(300) for s in (None, 1.0)], "id long, label string, split string, s double, pv array<double>").repartition(7)
    train = np.arange(300) % 5 > 0
    net = classify.mlp_fit_arrays(x[train], np.arange(300)[train] % 3, ["p0", "p1", "p2"], hidden=(8,), max_iter=9, batch=20)
    want = {i: f"p{k}" for i, k in zip(np.flatnonzero(~train).tolist(), net.probabilities(x[~train]).argmax(1))}
    # over the limit each epoch was once a single step over all rows
    got = classify.rated_each(df, "s", limit=50, hidden=(8,), max_iter=9, batch=20).where("recogniser = 'network'").collect()
    assert len(got) == 2 * 60 and {r.epochs for r in got} == {len(net.losses)} and all(r.pred == want[r.id] for r in got)
    near = {name: {(r.s, r.id): r.pred for r in classify.rated_each(df, "s", kinds, hidden=(8,), max_iter=1).where("recogniser = 'centroid'").collect()} for name, kinds in (("tasks", ("network", "centroid")), ("alone", ("centroid",)))}
    assert near["tasks"] == near["alone"] and len(near["alone"]) == 2 * 60


def test_a_fit_takes_the_same_steps_at_any_size(spark):
    rng = np.random.default_rng(7)
    x, names = rng.normal(size=(130, 4)).astype(np.float32), [f"p{i % 2}" for i in range(130)]
    df = spark.createDataFrame([(i, names[i], x[i].tolist()) for i in range(130)], "id long, label string, pv array<double>").repartition(5)
    want = classify.mlp_fit_arrays(x, np.arange(130) % 2, ["p0", "p1"], hidden=(8,), max_iter=40, batch=16, until=(1e-2, 3))
    for limit in (7, 50_000):  # over the limit each epoch was once a single step over all rows, and no rule ended it
        got = classify.mlp_fit(df, limit=limit, hidden=(8,), max_iter=40, batch=16, until=(1e-2, 3))
        assert got.losses == want.losses and got.classes == want.classes and len(got.losses) < 40


def test_both_fixtures_are_merged_from_every_number_of_parts(spark, sf):
    got = workloads.w12_partitions(spark, sf, counts=(1, 2, 4)).collect()
    assert sorted((r.fixture, r.parts) for r in got) == [(f, n) for f in ("fact_grid", "vectors") for n in (2, 3, 5)]
    assert all(r.max_abs_err < 1e-9 for r in got)


def test_states_of_many_wide_parts_are_handed_on(spark, monkeypatch):
    x, held = np.random.default_rng(5).normal(size=(60, 6)), []
    df = spark.createDataFrame([(i % 9, v.tolist()) for i, v in enumerate(x)], "part long, px array<double>").coalesce(1)
    monkeypatch.setattr(moments, "HELD", 2 * 6 * 6 * 8)
    monkeypatch.setattr(type(df), "mapInArrow", lambda df, run, *a, f=type(df).mapInArrow: (held.append(run), f(df, run, *a))[1])
    states = moments.partials(df.sortWithinPartitions("part"), part="part")
    assert np.allclose(moments.unpacked(moments.merge_over_tasks(states, 9, 2).collect()[0]).covariance(), np.cov(x.T))
    order = np.argsort(np.arange(60) % 9, kind="stable")
    batch = pa.RecordBatch.from_pydict({"part": order % 9, "x": pa.array(x[order].tolist(), pa.list_(pa.float64()))})
    assert [b.num_rows for b in held[0](iter([batch]))] == [1] * 9


def test_nearest_rows_are_found_without_copies_of_blocks(spark):
    rng = np.random.default_rng(11)
    x = rng.normal(size=(900, 4))
    x[450:460] = x[:10]  # ties go to the least id
    a, b = (spark.createDataFrame([(i, float(i), v.tolist()) for i, v in enumerate(rows)], "id long, mark double, v array<double>").repartition(3) for rows in (x[:300] + rng.normal(size=(300, 4)) * 0.2, x))
    sides = [attack.packed(df, "v", ("mark",), block_bytes=40 * 32) for df in (a, b)]
    plans = [side._jdf.queryExecution().optimizedPlan().toString() for side in sides]
    assert not any("Generate" in p or "FlatMapGroups" in p for p in plans)  # each block went once to every block of the other side
    got = attack.nearest_of(*sides, ("mark",), part_bytes=5000).first()
    near = ((np.array([r.v for r in a.orderBy("id").collect()])[:, None] - x[None]) ** 2).sum(2).argmin(1)
    assert got.n == 300 and got.rate == pytest.approx((near == np.arange(300)).mean()) and got.mark == pytest.approx(149.5)


def test_states_of_wide_rows_are_folded_in_place(spark, monkeypatch):
    held, rows = [], np.random.default_rng(12).normal(size=(4096, 1000))
    df = spark.createDataFrame([([1.0],)], "px array<double>")
    monkeypatch.setattr(type(df), "mapInArrow", lambda df, run, *a: held.append(run))
    moments.partials(df)
    batch = pa.RecordBatch.from_arrays([pa.array(np.zeros(4096, np.int64)), pa.ListArray.from_arrays(pa.array(np.arange(4097) * 1000, pa.int32()), pa.array(rows.ravel()))], ["part", "x"])
    tracemalloc.start()
    state = list(held[0](iter([batch, batch])))[0].to_pylist()[0]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60e6 and state["n"] == 8192  # a state takes 8 MB, the rows 33 MB
    assert np.allclose(moments._unpack(state["n"], state["mean"], state["scatter"]).covariance(0), np.cov(rows.T, ddof=0))


def test_states_of_few_wide_rows_travel_as_rows():
    for n in (1, 5, 20, 21, 40):
        rows = np.random.default_rng(n).normal(size=(n, 40))
        state = moments.Moments.of(rows)
        row = moments._pack(state)
        assert len(row["scatter"]) == 8 * min(n * 40, 40 * 41 // 2)
        got = moments.unpacked(row)
        assert got.n == n and np.allclose(got.scatter, state.scatter) and (got.mean == state.mean).all()
