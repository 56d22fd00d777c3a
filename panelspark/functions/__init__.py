"""SQL functions of the engine: register(spark) makes them usable in SQL text."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.kernels import dlp, slp


def _entry(kernel):
    def values(a: pd.Series, b: pd.Series, case: pd.Series) -> pd.Series:
        from ..operators.assembly import batch_values

        pa, pb = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
        out = np.zeros(len(pa))
        ca, cb = pa.reshape(-1, 3, 3), pb.reshape(-1, 3, 3)
        normal = np.cross(cb[:, 1] - cb[:, 0], cb[:, 2] - cb[:, 1])
        gb = np.linalg.norm(normal, axis=1)
        ga = np.linalg.norm(np.cross(ca[:, 1] - ca[:, 0], ca[:, 2] - ca[:, 1]), axis=1)
        for c in case.unique():
            r = np.flatnonzero((case == c).to_numpy())
            out[r] = np.real(batch_values(ca[r], cb[r], normal[r] / gb[r, None], ga[r] * gb[r], int(c), 3 if c == 0 else 5, kernel))
        return pd.Series(out)

    return F.pandas_udf(values, T.DoubleType())


@F.udtf(returnType="q int, x double, w double")
class GaussRule:
    def eval(self, n: int):
        x, w = np.polynomial.legendre.leggauss(n)
        for q in range(n):
            yield q, float((x[q] + 1) / 2), float(w[q] / 2)


@F.udtf(returnType="piece int, bytes long")
class SplitBlock:
    def eval(self, size: int, limit: int):
        queue, piece = [size], 0
        while queue:
            s = queue.pop(0)
            if s >= limit and s > 1:
                queue[:0] = [s - s // 2, s // 2]
            else:
                yield piece, s
                piece += 1


def frobenius(values: pd.Series) -> float:
    return float(np.sqrt((values**2).sum()))


def register(spark: SparkSession) -> None:
    """slp_entry, dlp_entry(corners a, corners b, case), gauss_rule(n), split_block(size, limit), frobenius(x), and
    the SQL-bodied common_vertices, box_dist and box_diam, which stay in generated code."""
    spark.udf.register("slp_entry", _entry(slp()))
    spark.udf.register("dlp_entry", _entry(dlp()))
    spark.udtf.register("gauss_rule", GaussRule)
    spark.udtf.register("split_block", SplitBlock)
    spark.udf.register("frobenius", _aggregate())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION common_vertices(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS INT RETURN size(array_intersect(a, b))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION box_dist(la ARRAY<DOUBLE>, ha ARRAY<DOUBLE>, lb ARRAY<DOUBLE>, hb ARRAY<DOUBLE>) RETURNS DOUBLE RETURN greatest(0D, la[0] - hb[0], lb[0] - ha[0], la[1] - hb[1], lb[1] - ha[1], la[2] - hb[2], lb[2] - ha[2])")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION box_diam(lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>) RETURNS DOUBLE RETURN greatest(hi[0] - lo[0], hi[1] - lo[1], hi[2] - lo[2])")


def _aggregate():
    def total(values: pd.Series) -> float:
        return frobenius(values)

    return F.pandas_udf(total, T.DoubleType())
