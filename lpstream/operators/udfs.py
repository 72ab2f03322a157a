"""The UDF surface: what built-in expressions can't say, each Arrow-batched."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.losses import log_cdf


def probit_logcdf(p: float):
    """Scalar Arrow UDF: log distribution function of the p-generalised normal."""

    @F.pandas_udf("double")
    def f(x: pd.Series) -> pd.Series:
        return pd.Series(log_cdf(x.to_numpy(float), p))

    return f


def medoid(p: float):
    """Grouped aggregate: number of the vector with the least (lower) median lp distance to the others (ties: the first)."""

    @F.pandas_udf("int")
    def f(rep: pd.Series, vec: pd.Series) -> int:
        order = np.argsort(rep.to_numpy())
        v = np.array(vec.tolist(), float)[order]
        d = (np.abs(v[:, None] - v[None]) ** p).sum(2)
        if len(v) == 1:
            return int(rep.iloc[0])
        others = d[~np.eye(len(v), dtype=bool)].reshape(len(v), -1)
        return int(rep.to_numpy()[order][np.argmin(np.round(np.sort(others, axis=1)[:, (others.shape[1] - 1) // 2], 6))])

    return f


@F.udtf(returnType="row_id bigint, col_id int, delta double")
class ExplodeUpdates:
    """Table function: a wide row to its non-zero updates."""

    def eval(self, row_id: int, values: list):
        for j, v in enumerate(values or []):
            if v:
                yield row_id, j, float(v)


def register(spark: SparkSession) -> None:
    """SQL names: lp_norm(array, p), poly_bucket(id, seed, rep, r), explode_updates(row, array)."""
    from ..functions.hashing import Hashes, poly_numpy

    @F.pandas_udf("double")
    def lp_norm(vec: pd.Series, p: pd.Series) -> pd.Series:
        return pd.Series([float((np.abs(np.asarray(v, float)) ** q).sum()) for v, q in zip(vec, p)])

    @F.pandas_udf("int")
    def poly_bucket(ids: pd.Series, seed: pd.Series, rep: pd.Series, r: pd.Series) -> pd.Series:
        out = np.zeros(len(ids), np.int32)
        keys = pd.DataFrame({"s": seed, "j": rep, "r": r})
        for (s, j, n), at in keys.groupby(["s", "j", "r"]).groups.items():
            out[at] = Hashes(int(s)).bucket_numpy(ids.to_numpy()[at], int(j), int(n))
        return pd.Series(out)

    spark.udf.register("lp_norm", lp_norm)
    spark.udf.register("poly_bucket", poly_bucket)
    spark.udtf.register("explode_updates", ExplodeUpdates)
