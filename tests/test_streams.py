"""Streams replayed from files."""

from datetime import datetime, timedelta

import numpy as np
from pyspark.sql import functions as F

from eigenveil import sources, streaming
from eigenveil.operators import moments
from eigenveil.operators.release import PrivateEigenRelease
from eigenveil.params import ReleaseParams


def test_stream_equals_batch_and_does_not_redraw(spark, sf, tmp_path):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    model = PrivateEigenRelease(ReleaseParams(nc=8, eps=8.0, key="k1", irw=8, irh=8)).fit(base)
    streaming.write_captures(base, tmp_path / "in", 2)
    streaming.write_captures(base.where("id < 100"), tmp_path / "in", 1)  # sent again
    released = streaming.perturbed(streaming.once_each(streaming.capture(spark, str(tmp_path / "in")), "30 days"), model)
    streaming.run_to_end(released, str(tmp_path / "out"), str(tmp_path / "log"))
    got = {r.id: r.pv for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert spark.read.parquet(str(tmp_path / "out")).count() == len(got) == base.count()
    want = {r.id: r.pv for r in model.release(base).df.collect()}
    assert all(np.allclose(got[i], want[i], atol=1e-9) for i in want)


def test_incremental_moments(spark, sf, tmp_path):
    base = sources.embedding_images(sources.table(spark, sf, "embeddings"))
    streaming.write_captures(base, tmp_path / "in", 3)
    sink = streaming.IncrementalMoments(spark, str(tmp_path / "state"))
    streaming.capture(spark, str(tmp_path / "in")).writeStream.foreachBatch(sink).option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start().awaitTermination()
    batch, state = sink.current()
    assert state.n == base.count() and np.allclose(state.covariance(), moments.covariance_one_round(base))
    sink(base, batch)  # a batch that comes again changes nothing
    assert sink.current()[1].n == state.n


def test_ledger_and_revocation(spark, tmp_path):
    rows = [(1, "a", 4.0), (1, "b", 4.0), (1, "c", 4.0), (2, "a", 8.0)]
    spark.createDataFrame(rows, "id long, release_id string, eps double").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("id long, release_id string, eps double").parquet(str(tmp_path / "in"))
    streaming.budget_ledger(stream, 9.0).writeStream.format("memory").queryName("ledger").outputMode("append").option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start().awaitTermination()
    got = spark.sql("SELECT id, sum(CAST(accepted AS INT)) AS n FROM ledger GROUP BY id").toPandas()
    assert dict(zip(got.id, got.n)) == {1: 2, 2: 1}
    kept = streaming.without_revoked(spark.range(5), spark.createDataFrame([(3,)], "id long"))
    assert sorted(r.id for r in kept.collect()) == [0, 1, 2, 4]


def test_windows_and_interval_join(spark, sf, tmp_path):
    events = sources.table(spark, sf, "events")
    assert streaming.counts_by_window(events, "1 hour").agg(F.sum("n")).first()[0] == events.count()
    assert streaming.visits(events).agg(F.sum("n")).first()[0] == events.count()
    t = datetime(2024, 1, 1)
    spark.createDataFrame([(1, t), (2, t)], "id long, ts timestamp").write.parquet(str(tmp_path / "c"))
    spark.createDataFrame([(1, t + timedelta(seconds=30)), (2, t + timedelta(hours=1))], "id long, ts timestamp").write.parquet(str(tmp_path / "r"))
    read = lambda p: spark.readStream.schema("id long, ts timestamp").parquet(str(tmp_path / p))
    joined = streaming.capture_to_result(read("c"), read("r"))
    streaming.run_to_end(joined, str(tmp_path / "out"), str(tmp_path / "log"))
    got = spark.read.parquet(str(tmp_path / "out")).collect()
    assert [(r.id, r.seconds) for r in got] == [(1, 30)]
