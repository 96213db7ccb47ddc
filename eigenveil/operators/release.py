"""The private release (M23-M23b), its guard and ledger.

``PrivateEigenRelease`` is an Estimator, its model a Transformer.  The model holds what
stays at the edge (mean, eigenfaces, bounds); only released vectors leave it, wrapped
with their budget, and the guard refuses rows that still carry raw columns.
"""

from __future__ import annotations

import contextlib
import io
import json
import re
import zlib
from dataclasses import asdict, dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import perturb
from ..params import ReleaseParams, check_budget, resolve, resolve_target
from . import cohort, imaging, noise, project, scaling, spectra

#: Columns that never leave the edge.
RAW = frozenset({"px", "score", "scaled", "centred", "text", "embedding", "face"})


@dataclass(frozen=True)
class ReleasedFrame:
    """Released rows with what they cost: per index and per record."""

    df: DataFrame
    eps: float | None
    delta: float
    nc: int
    key_id: str
    release_id: str
    #: id and reason of the rows that could not be released (edge only)
    rejected: DataFrame | None = None

    @property
    def eps_index(self) -> float:
        return float("inf") if self.eps is None else self.eps / self.delta

    @property
    def eps_record(self) -> float:
        return float("inf") if self.eps is None else self.nc * self.eps / self.delta


def renamed_from(df: DataFrame, raw: frozenset[str] = RAW) -> set[str]:
    """Output columns that the plan makes of a raw column by renaming alone, through any number of names."""
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        df.explain(extended=True)
    plan = text.getvalue().split("== Physical Plan ==")[0]
    # attribute number -> (name, number) of what it renames; names of attributes by number
    renames = {b: (x, a) for x, a, _, b in re.findall(r"(\w+)#(\d+)L? AS (\w+)#(\d+)L?", plan)}
    names = {n: x for x, n in re.findall(r"(\w+)#(\d+)L?", plan)}
    found = set()
    for _, a, y, b in re.findall(r"(\w+)#(\d+)L? AS (\w+)#(\d+)L?", plan):
        at, seen = b, set()
        while at in renames and at not in seen:
            seen.add(at)
            if renames[at][0] in raw:
                found.add(y)
            at = renames[at][1]
        if names.get(at) in raw:
            found.add(y)
    return found & set(df.columns)


def assert_released(frame: ReleasedFrame) -> DataFrame:
    """The rows, if they were released and no raw column is among their outputs, under its own or another name.

    Vectors other than the released one are refused whatever they are called.
    """
    if not isinstance(frame, ReleasedFrame):
        raise TypeError("only a ReleasedFrame may leave the edge")
    found = RAW & set(frame.df.columns)
    found |= {name for name, kind in frame.df.dtypes if name != "pv" and (kind.startswith(("array", "binary", "vector", "map", "struct")))}
    found |= renamed_from(frame.df)
    if found:
        raise ValueError(f"raw columns must not leave the edge: {sorted(found)}")
    return frame.df


class PrivateEigenRelease(Estimator):
    """Cohort, target size, eigenfaces of the training rows, bounds."""

    def __init__(self, params: ReleaseParams):
        super().__init__()
        self.settings = params

    def _fit(self, dataset: DataFrame) -> PrivateEigenModel:
        p = self.settings
        valid, rejected = imaging.split_valid(dataset)
        rows = cohort.keep_frequent(valid, p.imthresh) if p.imthresh > 1 else valid
        parts = cohort.split(rows, p.train)
        # all that is asked of the rows before the fit, from one reading
        asked = [f(c).alias(f"{c}_{name}") for c in ("w", "h") for name, f in (("min", F.min), ("max", F.max))]
        sides = parts.agg(*asked, F.first("ch").alias("ch"), F.sum((F.col("split") == "train").cast("long")).alias("n")).first()
        if sides["w_min"] is None:
            raise ValueError("no rows")
        irw, irh = resolve_target(p.irw, p.irh, sides["w_min"], sides["h_min"])
        p = resolve(replace(p, irw=irw, irh=irh), sides["ch"])
        train = parts.where("split = 'train'")
        if any(sides[f"{c}_{m}"] != side for c, side in (("w", irw), ("h", irh)) for m in ("min", "max")):
            train = self._sized(train, p)
        model = spectra.fit(train, p.nc, ddof=p.ddof, n=sides["n"])
        model.w, model.h, model.ch = irw, irh, len(model.mean) // (irw * irh)
        p = replace(p, nc=model.nc)
        if p.domain == "pixel":
            bounds = scaling.fit_bounds(project.centred(train, model.mean, out="score"), scope=p.scope)
        else:
            bounds = scaling.fit_bounds(project.scores(train, model), scope=p.scope)
        return PrivateEigenModel(p, model, bounds, rejected.select("id", "reason"))

    @staticmethod
    def _sized(rows: DataFrame, p: ReleaseParams) -> DataFrame:
        off = rows.where((F.col("w") != p.irw) | (F.col("h") != p.irh)).limit(1)
        return rows if off.isEmpty() else imaging.resample(rows, p.irw, p.irh)


class PrivateEigenModel(Model):
    def __init__(self, params: ReleaseParams, eigen: spectra.EigenModel, bounds: scaling.Bounds, rejected: DataFrame | None = None):
        super().__init__()
        self.settings, self.eigen, self.bounds, self.rejected = params, eigen, bounds, rejected

    @property
    def width(self) -> int:
        return len(self.eigen.mean) if self.settings.domain == "pixel" else self.eigen.nc

    @property
    def delta(self) -> float:
        return noise.sensitivity(self.width, self.settings.delta_mode)

    def scaled(self, df: DataFrame) -> DataFrame:
        """Edge only: scores (or centred pixels) scaled to [0, 1], in column ``scaled``."""
        made = project.centred(df, self.eigen.mean, out="score") if self.settings.domain == "pixel" else project.scores(df, self.eigen, digits=10)
        return made.withColumn("scaled", scaling.scaled("score", self.bounds, self.settings.clip)).drop("score")

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return self.release(dataset).df

    def release(self, df: DataFrame, release_id: str | None = None, eps: float | None = -1.0, key: str | None = None, keep: tuple[str, ...] = ("id", "label"), secret: bool = False) -> ReleasedFrame:
        """Released vectors ``pv``; every release_id (or key) draws its own noise.

        Rows with null, non-finite or wrongly sized images are left out and named, with
        the reason, in ``rejected``.
        """
        p = self.settings
        eps = p.eps if eps == -1.0 else check_budget(eps, allow_extreme=p.allow_extreme)
        release_id, key = release_id or p.release_id, key or p.key
        usable, rejected = imaging.split_valid(df, len(self.eigen.mean))
        made = self.scaled(usable)
        value = F.col("scaled") if eps is None else perturb("scaled", eps, self.delta, key, "id", release_id, secret=secret, snap=p.snap)
        rows = made.select(*[c for c in keep if c in made.columns], value.alias("pv"))
        return ReleasedFrame(rows, eps, self.delta, self.width, f"{zlib.crc32(key.encode()):08x}", release_id, rejected.select(*[c for c in ("id",) if c in df.columns], "reason"))

    def unscale(self, y: np.ndarray) -> np.ndarray:
        return self.bounds.lo + y * (self.bounds.hi - self.bounds.lo)


def publish(frame: ReleasedFrame, path: str, by: str | None = None) -> None:
    writer = assert_released(frame).write
    (writer.partitionBy(by) if by else writer).parquet(path)


def export(artefacts: dict[str, object], path: str, spark: SparkSession) -> None:
    """A model trained on released data as one JSON row; edge state is refused."""
    for name, value in artefacts.items():
        if isinstance(value, (PrivateEigenModel, spectra.EigenModel, scaling.Bounds)) or name in RAW:
            raise ValueError(f"{name} stays at the edge")
    text = json.dumps({k: v.tolist() if isinstance(v, np.ndarray) else v for k, v in artefacts.items()})
    spark.createDataFrame(pa.table({"value": [text]})).coalesce(1).write.text(path)


def save(model: PrivateEigenModel, path: str, spark: SparkSession) -> None:
    """The edge's own state."""
    e, b = model.eigen, model.bounds
    head = {**asdict(model.settings), "n": e.n, "ch": e.ch, "scope": b.scope}
    rows = [("head", json.dumps(head), []), ("mean", "", e.mean.tolist()), ("values", "", e.values.tolist()), *((f"v{i}", "", v.tolist()) for i, v in enumerate(e.vectors))]
    rows += [("lo", "", b.lo.tolist()), ("hi", "", b.hi.tolist())] if b.lo is not None else []
    names, texts, values = zip(*rows)
    spark.createDataFrame(pa.table({"name": list(names), "text": list(texts), "values": pa.array(list(values), pa.list_(pa.float64()))})).write.parquet(path)


def load(spark: SparkSession, path: str) -> PrivateEigenModel:
    rows = {r["name"]: r for r in spark.read.parquet(path).collect()}
    head = json.loads(rows["head"]["text"])
    n, ch, scope = head.pop("n"), head.pop("ch"), head["scope"]
    params = ReleaseParams(**head)
    get = lambda k: np.array(rows[k]["values"])
    vectors = np.array([rows[f"v{i}"]["values"] for i in range(sum(k[0] == "v" and k[1:].isdigit() for k in rows))])
    eigen = spectra.EigenModel(get("mean"), get("values"), vectors, n, params.irw, params.irh, ch)
    return PrivateEigenModel(params, eigen, scaling.Bounds(scope, get("lo") if "lo" in rows else None, get("hi") if "hi" in rows else None))


def account(releases: DataFrame) -> DataFrame:
    """Q10: per id the sums of eps_index and eps_record over ``releases(id, eps, delta, nc)``."""
    return releases.groupBy("id").agg(F.count("*").alias("n_releases"), F.sum(F.col("eps") / F.col("delta")).alias("eps_index"), F.sum(F.col("nc") * F.col("eps") / F.col("delta")).alias("eps_record"))
