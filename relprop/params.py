"""Parameters: named arrays, fixed lattice weights for exact checks, files."""

from __future__ import annotations

import hashlib
import json

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


class LatticeParams:
    """Weights from integer arithmetic on a hash of their name: the same in every engine, multiples of 1/4000."""

    def __init__(self, d: int = 2, seed: int = 0):
        self.d, self.seed = d, seed

    def weight(self, name: str, i: int, j: int) -> float:
        return (int(hashlib.md5(f"{self.seed}:{name}:{i}:{j}".encode()).hexdigest()[:8], 16) % 2001 - 1000) / 4000

    def category(self, domain: str, value: Column, j: int) -> Column:
        """Component j of the vector of a value; null has the zero vector."""
        text = F.concat(F.lit(f"{self.seed}:{domain}:"), value.cast("string"), F.lit(f":{j}"))
        n = F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % 2001 - 1000
        return F.coalesce(n.cast("double") / 4000, F.lit(0.0))


class ParamStore(dict):
    """name -> float array; flattens to one vector and back for gradients."""

    def flat(self) -> np.ndarray:
        return np.concatenate([self[k].ravel() for k in sorted(self)]) if self else np.zeros(0)

    def like(self, flat: np.ndarray) -> ParamStore:
        out, at = ParamStore(), 0
        for k in sorted(self):
            n = self[k].size
            out[k] = flat[at : at + n].reshape(self[k].shape)
            at += n
        return out

    @property
    def nbytes(self) -> int:
        return sum(v.nbytes for v in self.values())

    def to_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(k, list(map(int, v.shape)), v.ravel().tolist()) for k, v in sorted(self.items())]
        return spark.createDataFrame(rows, "name string, shape array<int>, data array<double>")

    @classmethod
    def from_frame(cls, df: DataFrame) -> ParamStore:
        return cls({r["name"]: np.array(r["data"], float).reshape(r["shape"]) for r in df.collect()})  # parameters only


def save_model(spark: SparkSession, path: str, params: ParamStore, spec: dict) -> None:
    """Parameters as Parquet beside a one-row JSON description."""
    params.to_frame(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/params")
    spark.createDataFrame([(json.dumps(spec, sort_keys=True),)], "spec string").coalesce(1).write.mode("overwrite").json(f"{path}/spec")


def load_model(spark: SparkSession, path: str) -> tuple[ParamStore, dict]:
    return ParamStore.from_frame(spark.read.parquet(f"{path}/params")), json.loads(spark.read.json(f"{path}/spec").first()["spec"])
