"""Kernels as SQL-callable functions: scalar Arrow functions and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from featgreedy.operators.kernel import top_triple
from featgreedy.session import ship


@F.pandas_udf("struct<s double, u array<double>, v array<double>>")
def leading_triple(c: pd.Series, q: pd.Series) -> pd.DataFrame:
    """Leading singular triple of a row-major matrix with ``q`` rows."""
    got = [top_triple(np.asarray(m, float).reshape(int(k), -1)) for m, k in zip(c, q, strict=True)]
    return pd.DataFrame({"s": [g[0] for g in got], "u": [g[1].tolist() for g in got], "v": [g[2].tolist() for g in got]})


@F.pandas_udf("array<double>")
def sum_arrays(x: pd.Series) -> list:
    """Grouped aggregate: element sums of arrays."""
    return np.sum(np.stack(x.to_numpy()), axis=0).tolist()


class ExplodeBlock:
    """Table function: rows of a column-major block."""

    def eval(self, x: list, n: int, t0: int):
        for p, v in enumerate(x):
            yield t0 + p % n, p // n, float(v)


class PowerTrace:
    """Table function: estimates of the largest singular value by sweep."""

    def eval(self, c: list, q: int, sweeps: int):
        m = np.asarray(c, float).reshape(q, -1)
        v = m[np.abs(m).sum(1).argmax()]
        for k in range(1, sweeps + 1):
            u = m @ (v / np.sqrt(v @ v))
            v = m.T @ (u / np.sqrt(u @ u))
            yield k, float(np.sqrt(v @ v))


def register(spark: SparkSession) -> None:
    spark.udf.register("leading_triple", leading_triple)
    spark.udtf.register("explode_block", F.udtf(ExplodeBlock, returnType="t long, l int, v double"))
    spark.udtf.register("power_trace", F.udtf(PowerTrace, returnType="k int, s double"))


ship(__name__)
