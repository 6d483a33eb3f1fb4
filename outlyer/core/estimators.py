"""The structure scorer as an object: parameters are checked when it is made, fitted state can be saved and loaded."""

from __future__ import annotations

import json
import pickle

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.families import FAMILIES
from ..operators.isolation import fit_scorer, score_points


class StructureScorer:
    """``StructureScorer(family="line", eps=0.03).fit(points).transform(points)``: points have pid and x."""

    def __init__(self, family: str | None = "line", eps: float = 0.03, forest: str = "hash", trees: int = 100, psi: int = 256, b: int = 2, m: int = 400, kind: str = "gauss", seed: int = 1):
        if family is not None and family not in FAMILIES:
            raise ValueError(f"unknown family {family}")
        if eps <= 0 or trees < 1 or m < 1 or not 2 <= b <= psi:
            raise ValueError("eps, trees and m must be positive, and 2 <= b <= psi")
        if kind not in ("binary", "gauss", "gauss05"):
            raise ValueError(f"unknown preference kind {kind}")
        self.params = {"family": family, "eps": eps, "forest": forest, "trees": trees, "psi": psi, "b": b, "m": m, "kind": kind, "seed": seed}
        self.models = self.forest = None

    def fit(self, points: DataFrame) -> StructureScorer:
        self.models, self.forest = fit_scorer(points, **self.params)
        return self

    def transform(self, points: DataFrame) -> DataFrame:
        """pid and score."""
        if self.forest is None:
            raise ValueError("fit comes before transform")
        return score_points(points, self.models, self.forest, self.params["eps"], self.params["kind"])

    def save(self, spark: SparkSession, path: str) -> None:
        """Parameters as JSON, models and trees as one row each."""
        models = [("model", i, None, bytearray(pickle.dumps((f.name, t)))) for i, (f, t) in enumerate(self.models or [])]
        trees = [("tree", i, None, bytearray(pickle.dumps(t))) for i, t in enumerate(self.forest.trees)]
        spark.createDataFrame([("params", 0, json.dumps(self.params | {"psi_used": self.forest.psi}), None), *models, *trees], "part string, no int, text string, body binary").write.parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> StructureScorer:
        """Only from a folder you trust: the rows are pickled."""
        from ..operators.isolation import Forest

        rows = spark.read.parquet(path).orderBy("part", "no").collect()
        params = json.loads(next(r["text"] for r in rows if r["part"] == "params"))
        psi = params.pop("psi_used")
        made = cls(**params)
        made.models = None if params["family"] is None else [(FAMILIES[n], t) for n, t in (pickle.loads(bytes(r["body"])) for r in rows if r["part"] == "model")]
        made.forest = Forest(params["forest"], psi, params["b"], seed=params["seed"])
        made.forest.trees = [pickle.loads(bytes(r["body"])) for r in rows if r["part"] == "tree"]
        return made


def assemble(df: DataFrame, cols: list[str], out: str = "x") -> DataFrame:
    """One array column of doubles; rows with a null or NaN feature are left out, and ``df.observe`` can count them before."""
    whole = [F.col(c).cast("double") for c in cols]
    keep = F.lit(True)
    for c in whole:
        keep = keep & c.isNotNull() & ~F.isnan(c)
    return df.where(keep).withColumn(out, F.array(*whole))


def scale(df: DataFrame, cols: list[str], how: str = "minmax", clip: tuple[float, float] | None = None) -> DataFrame:
    """Columns scaled by one aggregate row, broadcast: ``minmax`` to [0, 1], ``standard`` to mean 0 and deviation 1; constant columns become 0."""
    if how not in ("minmax", "standard"):
        raise ValueError(f"unknown scaling {how}")
    low = {c: F.min(c) if how == "minmax" else F.avg(c) for c in cols}
    wide = {c: F.max(c) - F.min(c) if how == "minmax" else F.stddev_pop(c) for c in cols}
    stats = df.agg(*[low[c].alias(f"_l_{c}") for c in cols], *[wide[c].alias(f"_w_{c}") for c in cols])
    out = df.crossJoin(F.broadcast(stats))
    for c in cols:
        v = F.coalesce(F.try_divide(F.col(c) - F.col(f"_l_{c}"), F.col(f"_w_{c}")), F.when(F.col(c).isNotNull(), 0.0))
        out = out.withColumn(c, F.greatest(F.lit(clip[0]), F.least(F.lit(clip[1]), v)) if clip else v)
    return out.drop(*[f"_{k}_{c}" for k in "lw" for c in cols])


def one_hot(df: DataFrame, col: str, values: list[str]) -> DataFrame:
    """One 0/1 column for each stated value; a null has none."""
    return df.select("*", *[F.coalesce((F.col(col) == v).cast("int"), F.lit(0)).alias(f"{col}_{v}") for v in values])
