"""Registered queries of methods, baselines, measures and helpers, each with its SQL where there is one.

Fitted axes cannot be seen from SQL, so projection, scaling and release are compared on
fixed orthonormal axes (entry (i, j) is (-1)**popcount(i AND j) / 8), and fitted ones by
what holds for any right solution: trace, squared norm, residual, projectors.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sources, streaming
from ..functions import laplace_pdf, perturb, register
from ..operators import attack, audit, baselines, classify, cohort, imaging, measures, moments, noise, project, relops, scaling, spectra
from ..operators.release import PrivateEigenModel
from ..params import ReleaseParams, cap_components, resolve_target
from .workloads import WORKLOADS, sources_free

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return sources.table(spark, sf_dir, name)


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sources.embedding_images(table(spark, sf_dir, "embeddings"))


def axes(k: int = 16) -> spectra.EigenModel:
    return spectra.EigenModel(np.zeros(64), np.ones(k), project.sign_axes(k), 0, 8, 8, 1)


def long(df: DataFrame, column: str, id_: str = "id", digits: int = 6) -> DataFrame:
    return df.select(id_, F.posexplode(column).alias("idx", "v")).select(id_, F.col("idx").cast("long").alias("idx"), (F.round(F.col("v").cast("double"), digits) + 0.0).alias("value"))


def _union(frames) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def one(spark: SparkSession, **values) -> DataFrame:
    return spark.createDataFrame(pa.table({k: [v] for k, v in values.items()}))


# --- SQL building blocks -----------------------------------------------------------

E = "e AS (SELECT vec_id, label, i AS idx, embedding[i + 1]::DOUBLE AS x FROM embeddings, range(0, 64) t(i))"
U = "((('0x' || substr(md5({}), 1, 12))::BIGINT) + 0.5) / 281474976710656.0"
LAP = "(-({b}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"
COV = f"WITH {E} SELECT a.idx AS i, b.idx AS j, round(covar_samp(a.x, b.x), 9) AS c FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2"
MEAN = f"WITH {E} SELECT idx, round(avg(x), 9) AS value FROM e GROUP BY 1"


def uniform(*parts: str) -> str:
    return "(" + U.format(" || '|' || ".join(parts)) + ")"


def laplace_sql(scale: str, *parts: str) -> str:
    return LAP.format(b=scale, u=uniform(*parts))


W = "w AS (SELECT k, j, (CASE WHEN bit_count(k & j) % 2 = 0 THEN 1.0 ELSE -1.0 END) / 8 AS a FROM range(0, 16) t(k), range(0, 64) s(j))"
S = f"{E}, {W}, s AS (SELECT vec_id, k, sum(x * a) AS z FROM e JOIN w ON j = idx GROUP BY 1, 2), b AS (SELECT k, min(z) AS lo, max(z) AS hi FROM s GROUP BY 1), q AS (SELECT vec_id, k, (z - lo) / (hi - lo) AS z FROM s JOIN b USING (k))"
CENTRES = f"{E}, m AS (SELECT label, idx, avg(x) AS c FROM e GROUP BY 1, 2), d AS (SELECT e.vec_id, e.label AS truth, m.label AS cand, sum((x - c) * (x - c)) AS d FROM e JOIN m USING (idx) GROUP BY 1, 2, 3), p AS (SELECT vec_id AS id, truth::VARCHAR AS label, arg_min(cand, (d, cand))::VARCHAR AS pred FROM d GROUP BY 1, 2)"
REPORT = "cells AS (SELECT label, pred, count(*) AS n FROM p GROUP BY 1, 2), names AS (SELECT label AS c FROM cells UNION SELECT pred FROM cells), r AS (SELECT c AS class, coalesce((SELECT sum(n) FROM cells WHERE label = c), 0)::BIGINT AS support, coalesce((SELECT sum(n) FROM cells WHERE pred = c), 0) AS predicted, coalesce((SELECT sum(n) FROM cells WHERE label = c AND pred = c), 0) AS hit FROM names), f AS (SELECT class, support, CASE WHEN predicted > 0 THEN hit / predicted ELSE 0.0 END AS p, CASE WHEN support > 0 THEN hit / support ELSE 0.0 END AS r FROM r), g AS (SELECT *, CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0.0 END AS f1 FROM f)"


# --- moments and spectra -----------------------------------------------------------


@query("mean_face", MEAN)
def mean_face(spark, sf_dir):
    return moments.vector_form(spark, moments.mean_face(vectors(spark, sf_dir)))


@query("merged_mean", MEAN)
def merged_mean(spark, sf_dir):
    parts = moments.by_part(vectors(spark, sf_dir).withColumn("part", F.pmod("id", F.lit(8))), "part")
    return moments.vector_form(spark, moments.merge_means((m.n, m.mean) for m in parts))


@query("covariance", COV)
@query("cov_one_round", COV)
def covariance(spark, sf_dir):
    return moments.long_form(spark, moments.covariance_one_round(vectors(spark, sf_dir)))


@query("cov_two_round", COV)
def cov_two_round(spark, sf_dir):
    return moments.long_form(spark, moments.covariance_two_round(vectors(spark, sf_dir)))


def _parts(spark, sf_dir, n=8):
    return moments.by_part(vectors(spark, sf_dir).withColumn("part", F.pmod("id", F.lit(n))), "part")


@query("merged_chain", COV)
def merged_chain(spark, sf_dir):
    return moments.long_form(spark, moments.merge_chain(_parts(spark, sf_dir)).covariance())


@query("merged_tree", COV)
def merged_tree(spark, sf_dir):
    """Eight parts merged over tasks, two at a time."""
    placed = vectors(spark, sf_dir).withColumn("part", F.pmod("id", F.lit(8)))
    row = moments.merge_over_tasks(moments.partials(placed, part="part"), 8, 2).collect()[0]
    return moments.long_form(spark, moments.unpacked(row).covariance())


@query("incremental_update", COV)
def incremental_update(spark, sf_dir):
    base, state = vectors(spark, sf_dir), None
    for k in range(3):
        state = moments.update(state, base.where(F.pmod("id", F.lit(3)) == k))
    return moments.long_form(spark, state.covariance())


@query("comoment", f"WITH {E} SELECT a.idx AS i, b.idx AS j, round(covar_pop(a.x, b.x) * count(*), 6) AS c FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2")
def comoment(spark, sf_dir):
    return moments.long_form(spark, moments.moments(vectors(spark, sf_dir)).scatter, 6)


@query(
    "merge_printed_error",
    f"WITH {E}, p AS (SELECT a.idx AS i, b.idx AS j, a.vec_id % 2 AS part, count(*) AS n, covar_samp(a.x, b.x) AS c, avg(a.x) AS u, avg(b.x) AS v FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2, 3), m AS (SELECT x.i, x.j, (x.c + y.c + (x.u - y.u) * (x.v - y.v) * x.n * y.n / (x.n + y.n)) / (x.n + y.n - 1) AS c FROM p x JOIN p y ON x.i = y.i AND x.j = y.j AND x.part = 0 AND y.part = 1), t AS (SELECT a.idx AS i, b.idx AS j, covar_samp(a.x, b.x) AS c FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2) SELECT round(max(abs(m.c - t.c)), 9) AS max_abs_err FROM m JOIN t USING (i, j)",
)
def merge_printed_error(spark, sf_dir):
    a, b = _parts(spark, sf_dir, 2)
    printed, right = moments.merge_pair(a, b, "as_printed"), moments.merge_pair(a, b)
    return one(spark, max_abs_err=round(measures.merge_error(printed.covariance(), right.covariance()), 9))


@query("gram_matrix", f"WITH {E} SELECT a.vec_id AS a, b.vec_id AS b, round(sum(a.x * b.x), 6) AS dot FROM e a JOIN e b USING (idx) GROUP BY 1, 2")
def gram_matrix(spark, sf_dir):
    """Products of all rows: packed blocks of rows meet by block pair, no row list is broadcast."""
    base = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    return relops.row_products(base).select("a", "b", (F.round("dot", 6) + 0.0).alias("dot"))


@query("eigen_trace", f"WITH {E}, c AS (SELECT idx, var_samp(x) AS v FROM e GROUP BY 1) SELECT round(sum(v), 8) AS total FROM c")
def eigen_trace(spark, sf_dir):
    return one(spark, total=round(float(spectra.solve_direct(moments.moments(vectors(spark, sf_dir)), 64).values.sum()), 8))


@query("eigen_frobenius", f"WITH {E}, c AS (SELECT a.idx AS i, b.idx AS j, covar_samp(a.x, b.x) AS c FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2) SELECT round(sum(c * c), 8) AS total FROM c")
def eigen_frobenius(spark, sf_dir):
    values = spectra.solve_direct(moments.moments(vectors(spark, sf_dir)), 64).values
    return one(spark, total=round(float((values**2).sum()), 8))


@query("eigen_residual_ok", "SELECT true AS residual_ok, true AS orthonormal_ok, true AS trace_ok")
def eigen_residual_ok(spark, sf_dir):
    state = moments.moments(vectors(spark, sf_dir))
    got = spectra.eigen_checks(state.covariance(), spectra.solve_direct(state, 64))
    return one(spark, residual_ok=got["residual"] < 1e-10, orthonormal_ok=got["orthonormal"] < 1e-10, trace_ok=abs(got["trace"] - got["sum_values"]) < 1e-10)


@query("subspace_equal", "SELECT route, true AS same FROM (VALUES ('gram'), ('mllib'), ('subspace')) t(route)")
def subspace_equal(spark, sf_dir):
    """Planted classes separate the leading axes, so the routes can be compared."""
    base = sources.planted_faces(table(spark, sf_dir, "embeddings")).persist()
    direct = spectra.solve_direct(moments.moments(base), 8)
    found = {"gram": spectra.solve_gram(base, 8), "mllib": spectra.solve_mllib(base, 8), "subspace": spectra.solve_subspace(base, 8, iters=60, tol=1e-12)}
    base.unpersist()
    return spark.createDataFrame([(k, spectra.same_subspace(direct.vectors, m.vectors) < 1e-4) for k, m in found.items()], "route string, same boolean")


# --- images ------------------------------------------------------------------------


@query("centred", f"WITH {E}, m AS (SELECT idx, avg(x) AS c FROM e GROUP BY 1) SELECT vec_id AS id, idx, round(x - c, 6) + 0.0 AS value FROM e JOIN m USING (idx)")
def centred(spark, sf_dir):
    base = vectors(spark, sf_dir)
    return long(project.centred(base.select("id", "px"), moments.mean_face(base)), "centred")


@query("flattened", f"WITH {E} SELECT vec_id AS id, idx, round(x, 6) + 0.0 AS value FROM e")
def flattened(spark, sf_dir):
    return long(imaging.flatten(vectors(spark, sf_dir).withColumn("rows", imaging.as_rows("px", 8, 8)), "rows"), "rows")


@query("vertical_flip", f"WITH {E} SELECT vec_id AS id, (7 - idx // 8) * 8 + idx % 8 AS idx, round(x, 6) + 0.0 AS value FROM e")
def vertical_flip(spark, sf_dir):
    return long(imaging.vertical_flip(vectors(spark, sf_dir)), "px")


@query("resample_nearest", "SELECT vec_id AS id, (y * 5 + x)::BIGINT AS idx, round(embedding[((y * 2 + 1) * 8 // 12) * 8 + ((x * 2 + 1) * 8 // 10) + 1]::DOUBLE, 6) + 0.0 AS value FROM embeddings, range(0, 5) a(x), range(0, 6) b(y)")
def resample_nearest(spark, sf_dir):
    return long(imaging.resample(vectors(spark, sf_dir), 5, 6), "px")


_SIDES = "s AS (SELECT greatest(1, list_max(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x: length(x)))) AS w, length(string_split(coalesce(text, ''), chr(10))) AS h FROM documents)"


@query("min_resolution", f"WITH {_SIDES} SELECT min(w)::INTEGER AS w_min, min(h)::INTEGER AS h_min FROM s")
def min_resolution(spark, sf_dir):
    return imaging.min_resolution(sources.text_sides(table(spark, sf_dir, "documents")))


@query("resolved_target", f"WITH {_SIDES}, m AS (SELECT min(w) AS w, min(h) AS h FROM s) SELECT (CASE WHEN 47 < w OR 62 < h THEN w ELSE 47 END)::BIGINT AS irw, (CASE WHEN 47 < w OR 62 < h THEN h ELSE 62 END)::BIGINT AS irh FROM m")
def resolved_target(spark, sf_dir):
    row = min_resolution(spark, sf_dir).first()
    w, h = resolve_target(47, 62, row["w_min"], row["h_min"])
    return one(spark, irw=w, irh=h)


@query("capped_nc", f"WITH {_SIDES.replace('AS h FROM', 'AS h, doc_id FROM')} SELECT doc_id AS id, nc::BIGINT AS nc, least(nc, w, h)::BIGINT AS capped FROM s, (VALUES (10), (47), (48), (63), (128)) t(nc)")
def capped_nc(spark, sf_dir):
    """The cap at the sides of each text's raster."""
    sides, cap = sources.text_sides(table(spark, sf_dir, "documents")), F.udf(cap_components, "long")
    return _union(sides.select("id", F.lit(nc).cast("long").alias("nc"), cap(F.lit(nc), "w", "h").alias("capped")) for nc in (10, 47, 48, 63, 128))


@query(
    "bigram_grid",
    "WITH c AS (SELECT doc_id, list_transform(regexp_extract_all(lower(text), '(?s).'), lambda x: unicode(x)) AS l FROM documents), p AS (SELECT doc_id, unnest(l[:-2]) AS a, unnest(l[2:]) AS b FROM c WHERE length(l) > 1), g AS (SELECT doc_id, (a % 62) * 47 + b % 47 AS cell, count(*) AS n FROM p GROUP BY 1, 2) SELECT doc_id AS id, cell::BIGINT AS idx, round(sqrt(n / sum(n) OVER (PARTITION BY doc_id))::FLOAT::DOUBLE, 5) AS value FROM g",
)
def bigram_grid(spark, sf_dir):
    return long(sources.bigram_grid(table(spark, sf_dir, "documents")), "px", digits=5).where("value > 0")


@query("fact_grid", "SELECT l_suppkey AS id, ((week(l_shipdate) - 1) * 50 + least(50, greatest(1, l_quantity::INTEGER)) - 1)::BIGINT AS idx, count(*)::DOUBLE AS value FROM lineitem GROUP BY 1, 2")
def fact_grid(spark, sf_dir):
    return long(sources.fact_grid(table(spark, sf_dir, "lineitem")), "px").where("value > 0")


@query("text_raster", "WITH l AS (SELECT doc_id, lang, string_split(coalesce(text, ''), chr(10)) AS l FROM documents) SELECT doc_id AS id, lang AS label, greatest(1, list_max(list_transform(l, lambda x: length(x))))::INTEGER AS w, len(l)::INTEGER AS h, coalesce(list_sum(list_transform(regexp_extract_all(array_to_string(l, ''), '(?s).'), lambda c: unicode(c))), 0)::BIGINT AS total FROM l")
def text_raster(spark, sf_dir):
    """Lines as rows: sides and the sum of all codes."""
    made = sources.text_raster(table(spark, sf_dir, "documents"))
    total = F.aggregate("px", F.lit(0.0), lambda s, x: s + x).cast("long").alias("total")
    return made.select("id", "label", "w", "h", total)


@query("to_gray", "SELECT doc_id AS id, i AS idx, round(((o + 2 * c) / 3)::FLOAT::DOUBLE, 4) + 0.0 AS value FROM (SELECT vec_id AS doc_id, i, embedding[i + 1]::DOUBLE AS o, embedding[64 - i]::DOUBLE AS c FROM embeddings, range(0, 64) t(i))")
def to_gray(spark, sf_dir):
    """Three channels (the vector and twice its reverse) averaged to one."""
    turned = vectors(spark, sf_dir).withColumn("r", F.reverse("px"))
    return long(imaging.to_gray(imaging.stack_channels(turned, ["px", "r", "r"])), "px", digits=4)


_STANDARD = {"unit_range": "(x - min(x) OVER p) / (max(x) OVER p - min(x) OVER p)", "zscore": "(x - avg(x) OVER p) / stddev_pop(x) OVER p"}
for _mode, _how in _STANDARD.items():

    def _standardised(spark, sf_dir, mode=_mode):
        return long(imaging.standardise(vectors(spark, sf_dir), mode), "px", digits=4)

    query(f"standardise_{_mode}", f"WITH {E} SELECT vec_id AS id, idx, round(({_how})::FLOAT::DOUBLE, 4) + 0.0 AS value FROM e WINDOW p AS (PARTITION BY vec_id)")(_standardised)


@query("rejected_rows", "SELECT vec_id AS id, CASE vec_id % 4 WHEN 0 THEN 'null' WHEN 1 THEN 'length' ELSE 'not finite' END AS reason FROM embeddings WHERE vec_id % 4 < 3")
def rejected_rows(spark, sf_dir):
    """What a release leaves out: every fourth row is whole, the others lack a vector, a value or a finite one."""
    px, k = F.col("px"), F.pmod("id", F.lit(4))
    broken = F.when(k == 1, F.slice(px, 1, 63)).when(k == 2, F.transform(px, lambda x, i: F.when(i == 5, F.lit(float("nan"))).otherwise(x))).when(k == 3, px)
    return imaging.split_valid(vectors(spark, sf_dir).withColumn("px", broken))[1].select("id", "reason")


def _axis(size: int, target: int, name: str) -> str:
    """For each target place the lower of its two source places and the share of the upper one."""
    return f"{name} AS (SELECT t, floor(p)::BIGINT AS lo, least({size - 1}, floor(p)::BIGINT + 1) AS hi, p - floor(p) AS f FROM (SELECT t, greatest(0.0::DOUBLE, least({size - 1}.0::DOUBLE, (t + 0.5::DOUBLE) * {size} / {target} - 0.5)) AS p FROM range(0, {target}) r(t)))"


@query("resample_bilinear", f"WITH {E}, {_axis(8, 5, 'xs')}, {_axis(8, 6, 'ys')}, c AS (SELECT ys.t * 5 + xs.t AS idx, cx.k AS xk, cy.k AS yk, CASE cx.k WHEN 0 THEN xs.lo ELSE xs.hi END + 8 * CASE cy.k WHEN 0 THEN ys.lo ELSE ys.hi END AS cell, CASE cx.k WHEN 0 THEN 1 - xs.f ELSE xs.f END * CASE cy.k WHEN 0 THEN 1 - ys.f ELSE ys.f END AS wt FROM xs, ys, range(0, 2) cx(k), range(0, 2) cy(k)) SELECT vec_id AS id, c.idx, round(sum(x * wt)::FLOAT::DOUBLE, 5) + 0.0 AS value FROM e JOIN c ON e.idx = cell GROUP BY 1, 2")
def resample_bilinear(spark, sf_dir):
    return long(imaging.resample(vectors(spark, sf_dir), 5, 6, "bilinear"), "px", digits=5)


# --- cohort ------------------------------------------------------------------------


def _langs(spark, sf_dir):
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))


@query("imthresh_keep", "SELECT lang AS label, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) >= 120")
def imthresh_keep(spark, sf_dir):
    return cohort.keep_frequent(_langs(spark, sf_dir), 120).groupBy("label").agg(F.count("*").alias("n"))


@query("imthresh_cap", "SELECT doc_id AS id, lang AS label FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY md5('cap|' || doc_id), doc_id) <= 50")
def imthresh_cap(spark, sf_dir):
    return cohort.cap_per_class(_langs(spark, sf_dir), 50)


@query("split_assign", f"SELECT doc_id AS id, CASE WHEN {uniform(chr(39) + 'split' + chr(39), 'doc_id')} < 0.7 THEN 'train' ELSE 'test' END AS split FROM documents")
def split_assign(spark, sf_dir):
    return cohort.split(_langs(spark, sf_dir)).select("id", "split")


@query("split_stratified", f"WITH r AS (SELECT doc_id AS id, lang, row_number() OVER (PARTITION BY lang ORDER BY {uniform(chr(39) + 'split' + chr(39), 'doc_id')}, doc_id) AS k, count(*) OVER (PARTITION BY lang) AS n FROM documents) SELECT id, CASE WHEN k <= round(0.7 * n) THEN 'train' ELSE 'test' END AS split FROM r")
def split_stratified(spark, sf_dir):
    return cohort.split(_langs(spark, sf_dir), stratify="label").select("id", "split")


# --- projection, scaling, noise ----------------------------------------------------


@query("scores_fixed_axes", f"WITH {E}, {W} SELECT vec_id AS id, k AS idx, round(sum(x * a), 6) + 0.0 AS value FROM e JOIN w ON j = idx GROUP BY 1, 2")
def scores_fixed_axes(spark, sf_dir):
    return long(project.scores(vectors(spark, sf_dir).select("id", "px"), axes()), "score")


@query("synth_fixed_axes", f"WITH {S}, y AS (SELECT vec_id, j, sum(z * a) AS v FROM s JOIN w USING (k) GROUP BY 1, 2) SELECT vec_id AS id, j AS idx, round(v, 6) + 0.0 AS value FROM y")
def synth_fixed_axes(spark, sf_dir):
    return long(project.synthesise(project.scores(vectors(spark, sf_dir).select("id", "px"), axes()), axes()), "face")


def _scaled(spark, sf_dir):
    made = project.scores(vectors(spark, sf_dir).select("id", "label", "px"), axes())
    return made.withColumn("scaled", scaling.scaled("score", scaling.fit_bounds(made)))


_REL = laplace_sql("0.25", "'k1'", "'r1'", "vec_id", "k")


@query("release_fixed_axes", f"WITH {S} SELECT vec_id AS id, k AS idx, round(z + {_REL}, 6) + 0.0 AS value FROM q")
def release_fixed_axes(spark, sf_dir):
    return long(noise.laplace(_scaled(spark, sf_dir).select("id", "scaled"), "scaled", 4.0, 1.0, "k1"), "scaled")


@query("reconstruct_fixed_axes", f"WITH {S}, y AS (SELECT vec_id, k, lo + (z + {_REL}) * (hi - lo) AS c FROM q JOIN b USING (k)) SELECT vec_id AS id, j AS idx, round(sum(c * a), 6) + 0.0 AS value FROM y JOIN w USING (k) GROUP BY 1, 2")
def reconstruct_fixed_axes(spark, sf_dir):
    """The attacker holds the axes and the edge's bounds; released values are scores."""
    made = project.scores(vectors(spark, sf_dir).select("id", "px"), axes())
    edge = PrivateEigenModel(ReleaseParams(nc=16, eps=4.0, key="k1", irw=8, irh=8, enforce_cap=False), axes(), scaling.fit_bounds(made))
    noisy = noise.laplace(made.select("id", scaling.scaled("score", edge.bounds).alias("pv")), "pv", 4.0, 1.0, "k1")
    return long(attack.reconstruct(noisy, axes(), domain="score", edge=edge), "guess")


_PIXEL = f"{E}, {W}, b AS (SELECT idx, min(x) AS lo, max(x) AS hi FROM e GROUP BY 1), y AS (SELECT vec_id, idx, lo + ((x - lo) / (hi - lo) + {laplace_sql('0.25', chr(39) + 'k1' + chr(39), chr(39) + 'r1' + chr(39), 'vec_id', 'idx')}) * (hi - lo) AS v FROM e JOIN b USING (idx)), c AS (SELECT vec_id, k, sum(v * a) AS c FROM y JOIN w ON j = idx GROUP BY 1, 2)"


@query("reconstruct_pixel_axes", f"WITH {_PIXEL} SELECT vec_id AS id, j AS idx, round(sum(c * a), 6) + 0.0 AS value FROM c JOIN w USING (k) GROUP BY 1, 2")
def reconstruct_pixel_axes(spark, sf_dir):
    """The same in the pixel domain: noise on scaled pixels, scaled back, projected on the attacker's axes."""
    made = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("score"))
    edge = PrivateEigenModel(ReleaseParams(nc=16, eps=4.0, key="k1", irw=8, irh=8, domain="pixel", enforce_cap=False), axes(), scaling.fit_bounds(made))
    noisy = noise.laplace(made.select("id", scaling.scaled("score", edge.bounds).alias("pv")), "pv", 4.0, 1.0, "k1")
    return long(attack.reconstruct(noisy, axes(), domain="pixel", edge=edge), "guess")


def _scaling(scope: str, lo: str, hi: str):
    sql = f"WITH {E} SELECT vec_id AS id, idx, round((x - {lo}) / ({hi} - {lo}), 6) + 0.0 AS value FROM e"

    @query(f"scaled_{scope}", sql)
    def run(spark, sf_dir):
        base = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("v"))
        return long(base.withColumn("v", scaling.scaled("v", scaling.fit_bounds(base, "v", scope))), "v")


_scaling("component", "min(x) OVER (PARTITION BY idx)", "max(x) OVER (PARTITION BY idx)")
_scaling("global", "min(x) OVER ()", "max(x) OVER ()")
_scaling("record", "min(x) OVER (PARTITION BY vec_id)", "max(x) OVER (PARTITION BY vec_id)")


@query("laplace_release", f"WITH {E} SELECT vec_id AS id, idx, round(x + {laplace_sql('0.25', chr(39) + 'k1' + chr(39), chr(39) + 'r1' + chr(39), 'vec_id', 'idx')}, 6) + 0.0 AS value FROM e")
def laplace_release(spark, sf_dir):
    return long(noise.laplace(vectors(spark, sf_dir).select("id", "px"), "px", 4.0, 1.0, "k1"), "px")


@query("laplace_sql_function", f"WITH {E} SELECT vec_id AS id, idx, round(x + {laplace_sql('0.25', chr(39) + 'k1' + chr(39), 'vec_id', 'idx')}, 6) + 0.0 AS value FROM e")
def laplace_sql_function(spark, sf_dir):
    register(spark)
    made = table(spark, sf_dir, "embeddings").selectExpr("vec_id AS id", "perturb(CAST(embedding AS ARRAY<DOUBLE>), 4D, 1D, 'k1', CAST(vec_id AS STRING)) AS v")
    return long(made, "v")


_Z = f"z AS (SELECT {laplace_sql('0.25', chr(39) + 'k1' + chr(39), chr(39) + 'r1' + chr(39), 'vec_id', 'i')} AS z FROM embeddings, range(0, 64) t(i))"


def _draws(spark, sf_dir):
    zero = F.transform("px", lambda x: F.lit(0.0))
    return vectors(spark, sf_dir).select(F.explode(perturb(zero, 4.0, 1.0, "k1", "id")).alias("z"))


@query("noise_moments", f"WITH {_Z} SELECT round(avg(z), 8) AS mean, round(avg(abs(z)), 8) AS mean_abs, round(var_samp(z), 8) AS variance, count(z) AS n FROM z")
def noise_moments(spark, sf_dir):
    return audit.noise_moments(_draws(spark, sf_dir)).select(*[F.round(c, 8).alias(c) for c in ("mean", "mean_abs", "variance")], "n")


@query("ks_stat", f"WITH {_Z}, u AS (SELECT CASE WHEN z < 0 THEN exp(z * 4) / 2 ELSE 1 - exp(-z * 4) / 2 END AS u FROM z), r AS (SELECT u, row_number() OVER (ORDER BY u) AS k, count(*) OVER () AS n FROM u) SELECT round(max(greatest(k / n - u, u - (k - 1) / n)), 8) AS ks, max(n) AS n FROM r")
def ks_stat(spark, sf_dir):
    return audit.ks_laplace(_draws(spark, sf_dir), 4.0).select(F.round("ks", 8).alias("ks"), "n")


@query("laplace_pdf_grid", f"WITH {E} SELECT vec_id AS id, idx, round(2.0 * exp(-abs(x - 0.5) * 4), 9) AS pdf FROM e")
def laplace_pdf_grid(spark, sf_dir):
    """The density at each component of the vectors."""
    x = vectors(spark, sf_dir).select("id", F.posexplode("px").alias("idx", "x"))
    return x.select("id", F.col("idx").cast("long").alias("idx"), F.round(laplace_pdf(F.col("x").cast("double"), F.lit(0.5), 4.0), 9).alias("pdf"))


@query("gaussian_release", f"WITH {E} SELECT vec_id AS id, idx, round(x + {noise.gaussian_sigma(0.5, 1e-5, 1.0)!r} * sqrt(-2 * ln({uniform(chr(39) + 'k1' + chr(39), chr(39) + 'g1' + chr(39), 'vec_id', 'idx', chr(39) + 'a' + chr(39))})) * cos(6.283185307179586 * {uniform(chr(39) + 'k1' + chr(39), chr(39) + 'g1' + chr(39), 'vec_id', 'idx', chr(39) + 'b' + chr(39))}), 5) + 0.0 AS value FROM e")
def gaussian_release(spark, sf_dir):
    return long(noise.gaussian(vectors(spark, sf_dir).select("id", "px"), "px", 0.5, 1e-5, 1.0, "k1"), "px", digits=5)


_PAIRS = [(0.0, 1.0), (0.25, 0.5), (0.9, 0.1)]


_RATIO = "p(v1, v2) AS (VALUES (0.0::DOUBLE, 1.0::DOUBLE), (0.25, 0.5), (0.9, 0.1)), r AS (SELECT v1, v2, max(abs(abs(x - v2 / {n}) - abs(x - v1 / {n})) * {eps}) AS ratio, {eps} * abs(v1 - v2) / {n} AS bound FROM e, p GROUP BY v1, v2)"


def _components(spark, sf_dir) -> DataFrame:
    return vectors(spark, sf_dir).select(F.explode("px").alias("x")).select(F.col("x").cast("double").alias("x"))


@query("ldp_ratio", f"WITH {E}, {_RATIO.format(n=1, eps=4)} SELECT v1, v2, round(ratio, 8) AS ratio, round(bound, 8) AS bound, ratio <= bound + 1e-9 AS holds FROM r")
def ldp_ratio(spark, sf_dir):
    """The greatest log ratio over the components of the vectors."""
    return audit.ldp_ratio(spark, 4.0, 1.0, _PAIRS, grid=_components(spark, sf_dir)).select("v1", "v2", F.round("ratio", 8).alias("ratio"), F.round("bound", 8).alias("bound"), "holds")


@query("gdp_ratio", f"WITH {E}, {_RATIO.format(n=100, eps=100)} SELECT round(v1 / 100, 6) AS v1, round(v2 / 100, 6) AS v2, ratio <= bound + 1e-9 AS holds FROM r")
def gdp_ratio(spark, sf_dir):
    return audit.gdp_ratio(spark, 1.0, 100, _PAIRS, grid=_components(spark, sf_dir)).select(F.round("v1", 6).alias("v1"), F.round("v2", 6).alias("v2"), "holds")


@query("budget_account", "SELECT user_id AS id, count(*) AS n_releases, count(*) * 4.0::DOUBLE AS eps_index, count(*) * 64.0::DOUBLE AS eps_record FROM events GROUP BY 1")
def budget_account(spark, sf_dir):
    from ..operators.release import account

    return account(table(spark, sf_dir, "events").select(F.col("user_id").alias("id"), F.lit(4.0).alias("eps"), F.lit(1.0).alias("delta"), F.lit(16).alias("nc")))


@query("sensitivity_modes", "WITH n AS (SELECT vec_id, len(embedding) AS nc FROM embeddings) SELECT vec_id AS id, nc::BIGINT AS nc, mode, round(CASE mode WHEN 'index' THEN 1 WHEN 'euclidean' THEN sqrt(nc) ELSE nc END, 9)::DOUBLE AS delta FROM n, (VALUES ('index'), ('euclidean'), ('l1')) b(mode)")
def sensitivity_modes(spark, sf_dir):
    """The sensitivity of each vector at its own length."""
    base = vectors(spark, sf_dir).select("id", F.size("px").cast("long").alias("nc"))
    known = {n: [noise.sensitivity(n, m) for m in ("index", "euclidean", "l1")] for n in [r[0] for r in base.select("nc").distinct().collect()]}
    deltas = spark.createDataFrame([(n, m, round(d, 9)) for n, ds in known.items() for m, d in zip(("index", "euclidean", "l1"), ds)], "nc long, mode string, delta double")
    return base.join(F.broadcast(deltas), "nc").select("id", "nc", "mode", "delta")


@query("empirical_sensitivity", f"WITH {E}, d AS (SELECT a.vec_id, b.vec_id AS o, sum(abs(a.x - b.x)) AS d FROM e a JOIN e b ON a.idx = b.idx AND a.vec_id < b.vec_id GROUP BY 1, 2) SELECT round(max(d), 6) AS delta FROM d")
def empirical_sensitivity(spark, sf_dir):
    """The exact pairwise form, in blocks; the bound by ranges is ``noise.empirical_sensitivity_bound``."""
    base = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("v"))
    return relops.greatest_l1(base).select(F.round("delta", 6).alias("delta"))


# --- recognition and measures ------------------------------------------------------


@query("nearest_face", f"WITH {E}, d AS (SELECT a.vec_id AS id, b.vec_id AS m, round(sum((a.x - b.x) * (a.x - b.x)), 9) AS d FROM e a JOIN e b ON a.idx = b.idx AND a.vec_id <> b.vec_id GROUP BY 1, 2) SELECT id, arg_min(m, (d, m)) AS match, round(min(d), 6) AS dist FROM d GROUP BY 1")
def nearest_face(spark, sf_dir):
    base = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("v"))
    return relops.nearest_one(base, base).select("id", "match", F.round("dist", 6).alias("dist"))


def _predicted(spark, sf_dir):
    base = vectors(spark, sf_dir).select("id", "label", F.col("px").cast("array<double>").alias("pv"))
    return classify.predict(base, classify.centroid_fit(base))


@query("nearest_centroid", f"WITH {CENTRES} SELECT id, label, pred FROM p")
def nearest_centroid(spark, sf_dir):
    return _predicted(spark, sf_dir).select("id", "label", "pred")


@query("confusion", f"WITH {CENTRES} SELECT label, pred, count(*) AS n FROM p GROUP BY 1, 2")
def confusion(spark, sf_dir):
    return measures.confusion(_predicted(spark, sf_dir))


@query("class_report", f"WITH {CENTRES}, {REPORT} SELECT class, support, round(p, 8) AS precision, round(r, 8) AS recall, round(f1, 8) AS f1 FROM g")
def class_report(spark, sf_dir):
    return measures.class_report(_predicted(spark, sf_dir)).select("class", "support", *[F.round(c, 8).alias(c) for c in ("precision", "recall", "f1")])


@query("weighted_report", f"WITH {CENTRES}, {REPORT} SELECT round(sum(support * p) / sum(support), 8) AS precision, round(sum(support * r) / sum(support), 8) AS recall, round(sum(support * f1) / sum(support), 8) AS f1, sum(support)::BIGINT AS n FROM g")
def weighted_report(spark, sf_dir):
    return measures.weighted_report(_predicted(spark, sf_dir)).select(*[F.round(c, 8).alias(c) for c in ("precision", "recall", "f1")], "n")


@query("macro_report", f"WITH {CENTRES}, {REPORT} SELECT round(avg(p), 8) AS precision, round(avg(r), 8) AS recall, round(avg(f1), 8) AS f1 FROM g WHERE support > 0")
def macro_report(spark, sf_dir):
    return measures.macro(_predicted(spark, sf_dir)).select(*[F.round(c, 8).alias(c) for c in ("precision", "recall", "f1")])


@query("accuracy", f"WITH {CENTRES} SELECT round(avg((label = pred)::INTEGER), 8) AS accuracy, count(*) AS n FROM p")
def accuracy(spark, sf_dir):
    return measures.accuracy(_predicted(spark, sf_dir)).select(F.round("accuracy", 8).alias("accuracy"), "n")


@query("majority", "WITH m AS (SELECT lang FROM documents GROUP BY 1 ORDER BY count(*) DESC, lang LIMIT 1) SELECT count(*) AS n, sum((documents.lang = m.lang)::INTEGER)::BIGINT AS hits FROM documents, m")
def majority(spark, sf_dir):
    got = classify.majority(_langs(spark, sf_dir))
    return got.agg(F.count("*").alias("n"), F.sum((F.col("label") == F.col("pred")).cast("int")).alias("hits"))


def _linked(eps: float) -> str:
    """Rate of probes whose nearest row of the other release (least id of ties) is their own, in SQL."""
    side = lambda key: f"SELECT vec_id, k, z + {laplace_sql(str(1 / eps), chr(39) + key + chr(39), chr(39) + 'r1' + chr(39), 'vec_id', 'k')} AS v FROM q"
    return f"WITH {S}, a AS ({side('k1')}), c AS ({side('k2')}), d AS (SELECT a.vec_id AS id, c.vec_id AS m, sum((a.v - c.v) * (a.v - c.v)) AS d FROM a JOIN c USING (k) GROUP BY 1, 2), g AS (SELECT id, arg_min(m, (d, m)) AS m FROM d GROUP BY 1) SELECT round(avg((id = m)::INTEGER), 6) AS rate, count(*) AS n, {eps}::DOUBLE AS eps FROM g"


@query("linkage", " UNION ALL ".join(f"SELECT * FROM ({_linked(e)})" for e in (0.5, 4.0, 8.0)))
def linkage(spark, sf_dir):
    """Two releases of every record under different keys."""
    made = _scaled(spark, sf_dir).select("id", F.col("scaled").alias("pv"))
    out = []
    for eps in (0.5, 4.0, 8.0):
        a, b = (noise.laplace(made, "pv", eps, 1.0, k) for k in ("k1", "k2"))
        out.append(attack.link(a, b).select(F.round("rate", 6).alias("rate"), "n").withColumn("eps", F.lit(eps)))
    return out[0].unionByName(out[1]).unionByName(out[2])


@query("k_average", "WITH r AS (SELECT vec_id, embedding, row_number() OVER (ORDER BY md5('kavg|' || vec_id), vec_id) AS k, count(*) OVER () AS n FROM embeddings), g AS (SELECT least((k - 1) // 5, n // 5 - 1) AS grp, i AS idx, embedding[i + 1]::DOUBLE AS x FROM r, range(0, 64) t(i)) SELECT grp::BIGINT AS grp, idx, round(avg(x), 6) + 0.0 AS value, count(*) AS n FROM g GROUP BY 1, 2")
def k_average(spark, sf_dir):
    got = baselines.k_average_keyed(vectors(spark, sf_dir), 5)
    return got.select("grp", F.col("idx").cast("long").alias("idx"), (F.round("value", 6) + 0.0).alias("value"), "n")


@query("k_average_nearest")
def k_average_nearest(spark, sf_dir):
    return baselines.k_average(vectors(spark, sf_dir), 5)


@query("global_dp_mean", f"WITH {E}, m AS (SELECT label, idx, avg(x) AS m, count(*) AS n FROM e GROUP BY 1, 2) SELECT label::VARCHAR AS label, idx, n, round(m + {laplace_sql('64 * 2.0 / (n * 4.0)', chr(39) + 'k1' + chr(39), chr(39) + 'gdp' + chr(39), 'label', 'idx')}, 6) + 0.0 AS value FROM m")
def global_dp_mean(spark, sf_dir):
    got = baselines.global_laplace_mean(vectors(spark, sf_dir), 4.0, "k1")
    return got.select("label", F.col("idx").cast("long").alias("idx"), "n", (F.round("value", 6) + 0.0).alias("value"))


_SPLIT = uniform("'split'", "vec_id")


@query("encrypted_match", f"WITH {E}, {W}, s AS (SELECT vec_id, k, sum(round_even(x * 64, 0)::BIGINT * (a * 64)::BIGINT)::BIGINT AS z FROM e JOIN w ON j = idx WHERE k < 4 GROUP BY 1, 2), g AS (SELECT vec_id FROM embeddings WHERE {_SPLIT} < 0.7 ORDER BY vec_id LIMIT 798), d AS (SELECT p.vec_id AS id, o.vec_id AS m, sum((p.z - o.z) * (p.z - o.z)) AS d FROM s p JOIN s o USING (k) JOIN g ON g.vec_id = o.vec_id WHERE p.vec_id IN (SELECT vec_id FROM embeddings WHERE {_SPLIT} >= 0.7) GROUP BY 1, 2) SELECT id, arg_min(m, (d, m)) AS match, variant FROM d, (VALUES ('interactive'), ('packed')) v(variant) GROUP BY id, variant")
def encrypted_match(spark, sf_dir):
    """Every test row against a gallery of the published size (training rows), on four fixed axes."""
    base = cohort.split(vectors(spark, sf_dir))
    gallery, probes = base.where("split = 'train'").orderBy("id").limit(798), base.where("split = 'test'")
    parts = [baselines.encrypted_match(probes, gallery, axes(4), v).select("id", "match", F.lit(v).alias("variant")) for v in ("interactive", "packed")]
    return parts[0].unionByName(parts[1])


@query("mlp_predictions")
def mlp_predictions(spark, sf_dir):
    base = sources.planted_faces(table(spark, sf_dir, "embeddings")).select("id", "label", F.col("px").cast("array<double>").alias("pv"))
    parts = cohort.split(base)
    net = classify.mlp_fit(parts.where("split = 'train'"), hidden=(32,), max_iter=30)
    return classify.predict(parts.where("split = 'test'"), net).select("id", "label", "pred", "confidence")


@query("library_recognisers")
def library_recognisers(spark, sf_dir):
    """Planted classes under noise, rated on rows that were not trained on."""
    base = sources.planted_faces(table(spark, sf_dir, "embeddings")).select("id", "label", F.col("px").cast("array<double>").alias("pv"))
    parts = cohort.split(noise.laplace(base, "pv", 8.0, 1.0, "k1")).persist()
    train, test = parts.where("split = 'train'"), parts.where("split = 'test'")
    out = [sources_free(measures.accuracy(classify.library_fit(train, kind).predict(test)).withColumn("kind", F.lit(kind))) for kind in ("perceptron", "logistic", "forest", "bayes")]
    parts.unpersist()
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


# --- the release through its model, and measures on what it gives --------------------


def _edge(spark, sf_dir, domain: str = "score") -> PrivateEigenModel:
    """A model on the fixed axes, with the bounds of the table: what it releases can be said in SQL."""
    base = vectors(spark, sf_dir)
    made = base.select("id", F.col("px").cast("array<double>").alias("score")) if domain == "pixel" else project.scores(base.select("id", "px"), axes())
    params = ReleaseParams(nc=16, eps=4.0, key="k1", irw=8, irh=8, domain=domain, enforce_cap=False)
    return PrivateEigenModel(params, axes(), scaling.fit_bounds(made))


def _noise(key: str, release: str, index: str, eps: float = 4.0) -> str:
    return laplace_sql(str(1 / eps), f"'{key}'", f"'{release}'", "vec_id", index)


@query("release_reissued", f"WITH {S} SELECT vec_id AS id, k AS idx, round(z + {_noise('k1', 'r2', 'k')}, 6) + 0.0 AS value FROM q")
def release_reissued(spark, sf_dir):
    """A second release of every record, with noise of its own."""
    return long(_edge(spark, sf_dir).release(vectors(spark, sf_dir), release_id="r2").df, "pv")


@query("release_pixel", f"WITH {E}, b AS (SELECT idx, min(x) AS lo, max(x) AS hi FROM e GROUP BY 1) SELECT vec_id AS id, idx, round((x - lo) / (hi - lo) + {_noise('k1', 'r1', 'idx')}, 6) + 0.0 AS value FROM e JOIN b USING (idx)")
def release_pixel(spark, sf_dir):
    """Scaled pixels under noise."""
    return long(_edge(spark, sf_dir, "pixel").release(vectors(spark, sf_dir)).df, "pv")


_RELEASED = f"{S}, r AS (SELECT vec_id, k, z + {_noise('k1', 'r1', 'k')} AS v FROM q)"


@query("exported_model", f"WITH {_RELEASED}, l AS (SELECT vec_id, label FROM embeddings) SELECT label::VARCHAR AS label, k AS idx, round(avg(v), 6) + 0.0 AS value FROM r JOIN l USING (vec_id) GROUP BY 1, 2")
def exported_model(spark, sf_dir):
    """A recogniser of released rows, written as JSON and read back."""
    from ..operators.release import export

    net = classify.centroid_fit(_edge(spark, sf_dir).release(vectors(spark, sf_dir)).df)
    path = f"{sources.shared_folder(spark)}/model-{uuid.uuid4().hex}"
    export({"classes": net.classes, "centres": net.centres}, path, spark)
    made = spark.read.text(path).select(F.from_json("value", "classes array<string>, centres array<array<double>>").alias("m"))
    each = made.select(F.explode(F.arrays_zip("m.classes", "m.centres")).alias("c")).select(F.col("c.classes").alias("label"), F.col("c.centres").alias("v"))
    return long(each, "v", "label")


_GUESSED = f"{_PIXEL}, g AS (SELECT vec_id, j AS idx, sum(c * a) AS g FROM c JOIN w USING (k) GROUP BY 1, 2)"


@query("reconstruction_quality", f"WITH {_GUESSED} SELECT vec_id AS id, round(avg((x - g) * (x - g)), 6) AS mse, round(sum(x * g) / sqrt(sum(x * x) * sum(g * g)), 6) AS cosine, round(10 * log10(max(x) * max(x) / avg((x - g) * (x - g))), 4) AS psnr FROM e JOIN g USING (vec_id, idx) GROUP BY 1")
def reconstruction_quality(spark, sf_dir):
    """Q9 of the pixel-domain attack on fixed axes."""
    base = vectors(spark, sf_dir).withColumn("truth", F.col("px").cast("array<double>"))
    edge = _edge(spark, sf_dir, "pixel")
    noisy = edge.release(base, keep=("id", "truth")).df
    rated = measures.reconstruction(attack.reconstruct(noisy, axes(), domain="pixel", edge=edge), "truth")
    return rated.select("id", F.round("mse", 6).alias("mse"), F.round("cosine", 6).alias("cosine"), F.round("psnr", 4).alias("psnr"))


@query("sensitivity_bound", f"WITH {E}, r AS (SELECT max(x) - min(x) AS r FROM e GROUP BY idx) SELECT round(sum(r), 6) AS l1, round(sqrt(sum(r * r)), 6) AS l2 FROM r")
def sensitivity_bound(spark, sf_dir):
    """M20a at scale: no pair of records lies further apart."""
    base = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("score"))
    return one(spark, l1=round(noise.empirical_sensitivity_bound(base), 6), l2=round(noise.empirical_sensitivity_bound(base, norm=2), 6))


_MEMBERS = f"t AS (SELECT vec_id, round(embedding[1]::DOUBLE, 3) AS s, {_SPLIT} < 0.7 AS member FROM embeddings)"


@query("membership_scores", f"WITH {_MEMBERS}, c AS (SELECT s, sum(member::INTEGER) AS i, sum((NOT member)::INTEGER) AS o FROM t GROUP BY 1), r AS (SELECT sum(i) OVER w / sum(i) OVER () - sum(o) OVER w / sum(o) OVER () AS d FROM c WINDOW w AS (ORDER BY s DESC)) SELECT round(greatest(0, max(d)), 9) AS advantage FROM r")
def membership_scores(spark, sf_dir):
    """Q14 on scores with ties: the first component for confidence, the training share for members."""
    base = cohort.split(vectors(spark, sf_dir)).select((F.round(F.col("px")[0].cast("double"), 3)).alias("confidence"), (F.col("split") == "train").alias("member"))
    return attack.membership(base).select(F.round("advantage", 9).alias("advantage"))


@query("memorisation_scores", f"WITH {_MEMBERS}, a AS (SELECT avg(s) FILTER (member) - avg(s) FILTER (NOT member) AS confidence_gap, avg((label = vec_id % 10)::INTEGER) FILTER (member) - avg((label = vec_id % 10)::INTEGER) FILTER (NOT member) AS accuracy_gap FROM t JOIN embeddings USING (vec_id)) SELECT round(accuracy_gap, 9) AS accuracy_gap, round(confidence_gap, 9) AS confidence_gap FROM a")
def memorisation_scores(spark, sf_dir):
    """Q14a on the same scores, the last digit of the id as the prediction."""
    base = cohort.split(vectors(spark, sf_dir)).select("split", "label", (F.col("id") % 10).cast("string").alias("pred"), F.round(F.col("px")[0].cast("double"), 3).alias("confidence"))
    got = attack.memorisation_gap(base.where("split = 'train'"), base.where("split = 'test'"))
    return got.select(*[(F.round(c, 9) + 0.0).alias(c) for c in ("accuracy_gap", "confidence_gap")])


# --- relational helpers ------------------------------------------------------------

for _how, _join in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):

    def _targets(spark, sf_dir, how=_how):
        return relops.with_targets(table(spark, sf_dir, "documents").select("doc_id", "lang"), table(spark, sf_dir, "labels"), how=how)

    query(f"join_targets_{_how}", f"SELECT doc_id, lang, quality, toxic FROM documents {_join} labels USING (doc_id)")(_targets)


@query("semi_known", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def semi_known(spark, sf_dir):
    return relops.keep_known(table(spark, sf_dir, "customer").select("c_custkey"), table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey")


@query("anti_revoked", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def anti_revoked(spark, sf_dir):
    return relops.drop_revoked(table(spark, sf_dir, "customer").select("c_custkey"), table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey")


def _events(spark, sf_dir):
    return table(spark, sf_dir, "events").withColumn("t", F.unix_timestamp(F.col("ts").cast("timestamp")))


@query("asof_latest", "WITH r AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) SELECT e.event_id, r.value AS latest FROM events e ASOF LEFT JOIN r ON e.user_id = r.user_id AND e.ts >= r.ts")
def asof_latest(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    r = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return relops.asof_latest(e.select("event_id", "user_id", "ts"), r, "user_id", "ts", "ts", "value").select("event_id", "latest")


@query("interval_pairs", "WITH e AS (SELECT event_id, user_id, event_type, floor(epoch(ts))::BIGINT AS t FROM events) SELECT a.event_id AS a, b.event_id AS b FROM e a JOIN e b ON a.user_id = b.user_id AND abs(a.t - b.t) <= 3600 AND a.event_type = 'purchase' AND b.event_type <> 'purchase'")
def interval_pairs(spark, sf_dir):
    e = _events(spark, sf_dir)
    left = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("a"), F.col("t").alias("ta"))
    right = e.where("event_type <> 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("t").alias("tb"))
    return relops.within_interval(left, right, "user_id", "ta", "tb", 3600).select("a", "b")


@query("range_bins", "SELECT event_id, lo::DOUBLE AS lo FROM events JOIN (SELECT k * 10.0 AS lo, k * 10.0 + 10.0 AS hi FROM range(0, 100) t(k)) ON value >= lo AND value < hi")
def range_bins(spark, sf_dir):
    bins = spark.range(100).select((F.col("id") * 10.0).alias("lo"), (F.col("id") * 10.0 + 10.0).alias("hi"))
    return relops.range_match(table(spark, sf_dir, "events").select("event_id", "value"), bins, "value", 25.0).select("event_id", "lo")


@query("theta_distance_pairs", f"WITH {E} SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.idx = b.idx AND a.vec_id < b.vec_id GROUP BY 1, 2 HAVING sum((a.x - b.x) * (a.x - b.x)) < 1.2")
def theta_distance_pairs(spark, sf_dir):
    v = vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("v"))
    return relops.close_pairs(v, 1.2)


for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _hinted(spark, sf_dir, hint=_hint):
        items, orders = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_extendedprice"), table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_orderpriority")
        sums = [got.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("total")) for got in relops.hinted_slices(items, orders, "k", hint)]
        if len(sums) > 1:  # exact sums, each slice's before the next slice is sent
            sums = [reduce(DataFrame.unionByName, map(sources_free, sums)).groupBy("o_orderpriority").agg(F.sum("n").alias("n"), F.sum("total").alias("total"))]
        return sums[0].select("o_orderpriority", "n", F.round("total", 2).cast("double").alias("total"))

    query(f"join_hints_{_hint}", "SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice::DECIMAL(18,2)), 2)::DOUBLE AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(_hinted)


def _quantity():
    return F.sum(F.col("l_quantity").cast("long")).alias("qty")



@query("cube_flags", "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS gid, sum(l_quantity::BIGINT)::BIGINT AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_flags(spark, sf_dir):
    return relops.cube_metrics(table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], _quantity())


@query("rollup_dates", "SELECT year(l_shipdate)::INTEGER AS y, month(l_shipdate)::INTEGER AS m, grouping_id(year(l_shipdate), month(l_shipdate))::BIGINT AS gid, sum(l_quantity::BIGINT)::BIGINT AS qty FROM lineitem GROUP BY ROLLUP (year(l_shipdate), month(l_shipdate))")
def rollup_dates(spark, sf_dir):
    return relops.rollup_metrics(table(spark, sf_dir, "lineitem").select(F.year("l_shipdate").alias("y"), F.month("l_shipdate").alias("m"), "l_quantity"), ["y", "m"], _quantity())


_GSETS = "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"


@query("gsets_flags", _GSETS.format("lineitem"))
def gsets_flags(spark, sf_dir):
    return spark.sql(_GSETS.format("{t}"), t=table(spark, sf_dir, "lineitem"))


@query("topk_global", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
def topk_global(spark, sf_dir):
    return relops.top_k(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice"), [F.desc("l_extendedprice"), F.col("l_orderkey"), F.col("l_linenumber")], 20)


@query("topk_per_supplier", "SELECT l_suppkey, l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber)::INTEGER AS rank FROM lineitem QUALIFY rank <= 3")
def topk_per_supplier(spark, sf_dir):
    got = relops.top_k_per(table(spark, sf_dir, "lineitem"), "l_suppkey", [F.desc("l_extendedprice"), F.col("l_orderkey"), F.col("l_linenumber")], 3, salt=F.col("l_orderkey"))
    return got.select("l_suppkey", "l_orderkey", "l_linenumber", "rank")


def _running(spark, sf_dir):
    return relops.running(table(spark, sf_dir, "events").select("user_id", "event_id", "ts", F.round(F.col("value") * 100).cast("long").alias("v")), "user_id", ["ts", "event_id"], "v")


_RW = "WITH e AS (SELECT user_id, event_id, ts, round(value * 100)::BIGINT AS v FROM events) SELECT event_id, {} FROM e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"


@query("win_running_budget", _RW.format("(sum(v) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))::BIGINT AS running_sum"))
def win_running_budget(spark, sf_dir):
    return _running(spark, sf_dir).select("event_id", "running_sum")


@query("win_moving_mean", _RW.format("round(avg(v) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING), 6) AS moving_mean"))
def win_moving_mean(spark, sf_dir):
    return _running(spark, sf_dir).select("event_id", F.round("moving_mean", 6).alias("moving_mean"))


@query("win_lag_lead", _RW.format("lag(v) OVER w AS previous, lead(v) OVER w AS following, first(v) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS first_value, last(v) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_value"))
def win_lag_lead(spark, sf_dir):
    return _running(spark, sf_dir).select("event_id", "previous", "following", "first_value", "last_value")


@query("win_ranks", "SELECT o_orderkey, (row_number() OVER w)::INTEGER AS rn, (rank() OVER w)::INTEGER AS rk, (dense_rank() OVER w)::INTEGER AS dr, (ntile(4) OVER w)::INTEGER AS nt, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_ranks(spark, sf_dir):
    got = relops.ranks(table(spark, sf_dir, "orders"), "o_custkey", [F.col("o_orderdate"), F.col("o_orderkey")])
    return got.select("o_orderkey", "rn", "rk", "dr", "nt", F.round("pr", 9).alias("pr"), F.round("cd", 9).alias("cd"))


@query("dedupe_text", "SELECT min(doc_id) AS doc_id, md5(text) AS digest, count(*) AS copies FROM documents GROUP BY text")
def dedupe_text(spark, sf_dir):
    got = relops.dedupe(table(spark, sf_dir, "documents").select(F.md5("text").alias("digest"), "doc_id"), ["digest"], "doc_id")
    return got.select("doc_id", "digest", "copies")


@query("distinct_users", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def distinct_users(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("approx_users", "SELECT event_type, count(DISTINCT user_id) AS users, true AS near FROM events GROUP BY 1")
def approx_users(spark, sf_dir):
    """Exact counts, and whether the sketch's lie within a tenth of them."""
    got = table(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("a"))
    return got.select("event_type", "users", (F.abs(F.col("a") - F.col("users")) <= 0.1 * F.col("users")).alias("near"))


@query("shape_summary", "WITH m AS (SELECT l_returnflag, avg(l_quantity) AS m, stddev_pop(l_quantity) AS s FROM lineitem GROUP BY 1), f AS (SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2), t AS (SELECT l_returnflag, arg_min(l_linenumber, (-n, l_linenumber)) AS mode FROM f GROUP BY 1) SELECT l_returnflag, round(avg((l_quantity - m) ** 3) / max(s) ** 3, 6) AS skew, round(quantile_cont(l_quantity, 0.9)::DOUBLE, 6) AS p90, max(mode)::BIGINT AS mode, max(l_orderkey) FILTER (l_quantity = 50)::BIGINT AS last_large FROM lineitem JOIN m USING (l_returnflag) JOIN t USING (l_returnflag) GROUP BY 1")
def shape_summary(spark, sf_dir):
    q = F.col("l_quantity").cast("double")
    mode = F.mode("l_linenumber", True).cast("long").alias("mode")
    last = F.max_by("l_orderkey", F.when(q == 50, F.col("l_orderkey"))).cast("long").alias("last_large")
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.skewness(q), 6).alias("skew"), F.round(F.percentile(q, 0.9), 6).alias("p90"), mode, last)


@query("win_range", "SELECT event_id, sum(1) OVER w AS span_n, sum(event_id) OVER w AS span_sum FROM (SELECT event_id, user_id, epoch(ts)::BIGINT AS t FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY t RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)")
def win_range(spark, sf_dir):
    """A frame by time, in seconds to the nearest even: the day up to each event of its user."""
    seconds = F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")
    got = relops.moving_range(table(spark, sf_dir, "events").withColumn("t", seconds), "user_id", "t", "event_id", 86_400)
    return got.select("event_id", "span_n", "span_sum")


_SUBQUERIES = """
SELECT o_custkey, count(*) AS n, sum(CASE WHEN o_totalprice > (SELECT avg(o_totalprice) FROM orders) THEN 1 ELSE 0 END) AS dear
FROM orders o
WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey < 10)
AND EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)
GROUP BY o_custkey
"""


@query("subqueries", _SUBQUERIES.replace("END) AS dear", "END)::BIGINT AS dear"))
def subqueries(spark, sf_dir):
    """A scalar, an IN and a correlated EXISTS subquery, as Spark SQL over the tables."""
    for name in ("orders", "customer", "lineitem"):
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark.sql(_SUBQUERIES)


_HALVED = "WITH RECURSIVE c AS (SELECT event_type, count(*) AS n FROM events GROUP BY event_type), s(event_type, n, step, eps) AS (SELECT event_type, n, 1, 8.0{d} FROM c UNION ALL SELECT event_type, n, step + 1, eps / 2 FROM s WHERE step < 8 AND step < n) SELECT event_type, n, step, round(eps, 6) AS eps, round(sum(eps) OVER (PARTITION BY event_type ORDER BY step), 6) AS spent FROM s"


@query("budget_halving", _HALVED.format(d="::DOUBLE"))
def budget_halving(spark, sf_dir):
    """A recursive query: releases of each type of event that halve their budget, and what they spend in all."""
    table(spark, sf_dir, "events").createOrReplaceTempView("events")
    return spark.sql(_HALVED.format(d="D"))


@query("pixel_rows", f"WITH {E} SELECT vec_id AS id, idx, round(x, 6) + 0.0 AS value FROM e")
def pixel_rows(spark, sf_dir):
    """The table function in SQL."""
    register(spark)
    vectors(spark, sf_dir).select("id", F.col("px").cast("array<double>").alias("v")).createOrReplaceTempView("faces_for_rows")
    return spark.sql("SELECT id, p.idx, round(p.value, 6) + 0.0D AS value FROM faces_for_rows, LATERAL explode_pixels(v) AS p")


@query("label_mean_vector", f"WITH {E} SELECT label, idx, round(avg(x), 6) + 0.0 AS value FROM e GROUP BY 1, 2")
def label_mean_vector(spark, sf_dir):
    """The vector aggregate by label."""
    from ..functions import mean_vector

    got = table(spark, sf_dir, "embeddings").groupBy("label").agg(mean_vector()("embedding").alias("m"))
    return long(got, "m", "label")


for _name, _sql in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    def _setop(spark, sf_dir, op=_sql):
        return spark.sql(f"SELECT c_nationkey AS k FROM {{c}} {op} SELECT s_nationkey AS k FROM {{s}}", c=table(spark, sf_dir, "customer"), s=table(spark, sf_dir, "supplier"))

    query(f"setop_{_name}", f"SELECT c_nationkey AS k FROM customer {_sql} SELECT s_nationkey AS k FROM supplier")(_setop)


@query("pivot_types", "SELECT o_orderstatus, " + ", ".join(f"count(*) FILTER (o_orderpriority = '{p}') AS \"{p}\"" for p in ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")) + " FROM orders GROUP BY 1")
def pivot_types(spark, sf_dir):
    return relops.pivot_counts(table(spark, sf_dir, "orders"), "o_orderstatus", "o_orderpriority", ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"])


@query("unpivot_vec", f"WITH {E} SELECT vec_id, idx::INTEGER AS idx, round(x, 6) + 0.0 AS value FROM e")
def unpivot_vec(spark, sf_dir):
    return relops.unpivot_vector(table(spark, sf_dir, "embeddings"), "vec_id", "embedding").select("vec_id", "idx", (F.round(F.col("value").cast("double"), 6) + 0.0).alias("value"))


@query("json_props", "SELECT event_id, (props::JSON ->> 'k')::BIGINT AS k FROM events")
def json_props(spark, sf_dir):
    return relops.parse_props(table(spark, sf_dir, "events")).select("event_id", "k")


@query("date_parts", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, dayofyear(o_orderdate)::INTEGER AS d, date_diff('day', date_trunc('month', o_orderdate), o_orderdate)::INTEGER AS dom0 FROM orders")
def date_parts(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.dayofyear("o_orderdate").alias("d"), F.datediff("o_orderdate", F.trunc("o_orderdate", "month")).alias("dom0"))


@query("sample_keyed", f"SELECT doc_id FROM documents WHERE {uniform(chr(39) + 's' + chr(39), 'doc_id')} < 0.2")
def sample_keyed(spark, sf_dir):
    return relops.sample_keyed(table(spark, sf_dir, "documents").select("doc_id"), 0.2, "s", "doc_id")


@query("sample_strata", f"SELECT doc_id FROM documents WHERE {uniform(chr(39) + 's' + chr(39), 'doc_id')} < CASE lang WHEN 'en' THEN 0.1 WHEN 'fr' THEN 0.5 ELSE 0.0 END")
def sample_strata(spark, sf_dir):
    return relops.sample_strata(table(spark, sf_dir, "documents").select("doc_id", "lang"), "lang", {"en": 0.1, "fr": 0.5}, "s", "doc_id").select("doc_id")


@query("stat_summary", "SELECT l_returnflag, round(var_samp(l_quantity), 6) AS var, round(covar_samp(l_quantity, l_discount), 6) AS cov, round(corr(l_quantity, l_extendedprice), 6) AS cor, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY 1")
def stat_summary(spark, sf_dir):
    q, x, d = "l_quantity", "l_extendedprice", "l_discount"
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.var_samp(q), 6).alias("var"), F.round(F.covar_samp(q, d), 6).alias("cov"), F.round(F.corr(q, x), 6).alias("cor"), F.round(F.regr_slope(x, q), 4).alias("slope"))


_TW = "SELECT epoch_us({s})::BIGINT AS start_us, event_type, count(*) AS n FROM {f} GROUP BY 1, 2"


def _window_rows(df: DataFrame) -> DataFrame:
    return df.select(F.unix_micros("start").alias("start_us"), "event_type", "n")


@query("win_tumbling", _TW.format(s="time_bucket(INTERVAL 1 HOUR, ts)", f="events"))
def win_tumbling(spark, sf_dir):
    return _window_rows(streaming.counts_by_window(table(spark, sf_dir, "events"), "1 hour"))


@query("win_sliding", _TW.format(s="time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE", f="events, range(0, 2) t(k)"))
def win_sliding(spark, sf_dir):
    return _window_rows(streaming.counts_by_window(table(spark, sf_dir, "events"), "1 hour", "30 minutes"))


@query("win_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, epoch_us(min(ts))::BIGINT AS start_us, count(*) AS n FROM s GROUP BY user_id, k")
def win_session(spark, sf_dir):
    return streaming.visits(table(spark, sf_dir, "events")).select("user_id", F.unix_micros("start").alias("start_us"), "n")


@query("accuracy_drop")
def accuracy_drop(spark, sf_dir):
    """Points of F1 lost by the network at each budget against no noise."""
    return measures.drop(WORKLOADS["w5_planted"](spark, sf_dir).where("recogniser = 'network'"))


@query("epochs_to_converge")
def epochs_to_converge(spark, sf_dir):
    """The first epoch after which the loss stands still; the network is trained until that is known."""
    tol, patience = 1e-3, 3
    return measures.epochs_to_converge(WORKLOADS["w4_training_loss"](spark, sf_dir, until=(tol, patience)), tol, patience)


def _members(spark, sf_dir):
    base = cohort.split(noise.laplace(sources.planted_faces(table(spark, sf_dir, "embeddings")).select("id", "label", F.col("px").cast("array<double>").alias("pv")), "pv", 8.0, 1.0, "k1"))
    net = classify.mlp_fit(base.where("split = 'train'"), hidden=(64,), max_iter=60)
    return classify.predict(base, net).withColumn("member", F.col("split") == "train")


@query("membership_inference")
def membership_inference(spark, sf_dir):
    """Advantage of telling training rows from others by the confidence of a model of released rows."""
    return attack.membership(_members(spark, sf_dir))


@query("memorisation_gap")
def memorisation_gap(spark, sf_dir):
    rated = _members(spark, sf_dir)
    return attack.memorisation_gap(rated.where("member"), rated.where("NOT member"))


@query("event_grid", "SELECT user_id, day, sum(n)::BIGINT AS n FROM (SELECT user_id, ts::DATE AS day, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1, 2")
def event_grid(spark, sf_dir):
    grid = sources.event_windows(table(spark, sf_dir, "events"))
    return grid.select("user_id", "day", F.aggregate("px", F.lit(0.0), lambda a, x: a + x).cast("long").alias("n"))


@query("incremental_stream")
def incremental_stream(spark, sf_dir):
    """Covariance diagonal of a state folded batch by batch from a replayed stream."""
    import time

    folder = f"{sources.shared_folder(spark)}/moments-{time.time_ns()}"
    streaming.write_captures(vectors(spark, sf_dir), f"{folder}/in", 3)
    sink = streaming.IncrementalMoments(spark, f"{folder}/state")
    streaming.capture(spark, f"{folder}/in").writeStream.foreachBatch(sink).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start().awaitTermination()
    return moments.vector_form(spark, sink.current()[1].covariance().diagonal())


SQL["incremental_stream"] = f"WITH {E} SELECT idx, round(var_samp(x), 9) AS value FROM e GROUP BY 1"

QUERIES |= WORKLOADS

SQL["w1_dataset"] = f"WITH k AS (SELECT lang FROM documents GROUP BY 1 HAVING count(*) >= 100) SELECT lang AS label, CASE WHEN {uniform(chr(39) + 'split' + chr(39), 'doc_id')} < 0.7 THEN 'train' ELSE 'test' END AS split, count(*) AS n FROM documents JOIN k USING (lang) GROUP BY 1, 2"
SQL["w14_capture"] = f"WITH {S} SELECT vec_id AS id, k AS idx, round(z + {laplace_sql('0.125', chr(39) + 'k1' + chr(39), chr(39) + 'r1' + chr(39), 'vec_id', 'k')}, 6) + 0.0 AS value FROM q"
