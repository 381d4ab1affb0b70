"""Arrow-backed functions for SQL users: the weight, a series statistic, and the aligner as a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from alignspark.params import AlignParams


def weight_udf(p: AlignParams):
    """The tuple weight as a vectorised function; equal to the column expression."""

    @F.pandas_udf(DoubleType())
    def weight(lam: pd.Series, d: pd.Series) -> pd.Series:
        return (p.k1 * lam * (lam - 1) / 2 + p.b) / (p.k2 * d + p.c)

    return weight


@F.pandas_udf(DoubleType())
def delta_udaf(idx: pd.Series, val: pd.Series) -> float:
    """Mean absolute difference of successive values in row order."""
    v = val.to_numpy(dtype=float)[np.argsort(idx.to_numpy(), kind="stable")]
    return float(np.abs(np.diff(v)).mean()) if len(v) > 1 else float("nan")


def register_candidates(spark: SparkSession) -> None:
    """Registers ``align_candidates(TABLE(...) PARTITION BY grp, m, theta, beta)``: one row a candidate tuple."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="grp string, x array<long>, lam int, spread_us long")
    class Candidates:
        def __init__(self):
            self.rows = []

        def eval(self, row, m: int, theta: int, beta: int):
            self.rows.append((row["grp"], row["sid"], row["idx"], row["ts_us"], row["val"]))
            self.args = (m, theta, beta)

        def terminate(self):
            if not self.rows:
                return
            from alignspark.operators.candidates import expand_block, matrices

            m, theta, beta = self.args
            for grp, pdf in pd.DataFrame(self.rows, columns=["grp", "sid", "idx", "ts_us", "val"]).groupby("grp"):
                times, _, has, first = matrices(pdf, m)
                x, lam, spread = expand_block(times, has, m, theta, beta, first, first + len(times) - 1, first)
                for row, count, gap in zip(x.tolist(), lam.tolist(), spread.tolist()):
                    yield grp, row, count, gap

    spark.udtf.register("align_candidates", Candidates)


def register_align_series(spark: SparkSession) -> None:
    """Registers ``align_series(TABLE(...) PARTITION BY grp, m, theta, beta, method)``."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="grp string, pos long, x array<long>, w_fp long")
    class AlignSeries:
        def __init__(self):
            self.rows = []
            self.args = None

        def eval(self, row, m: int, theta: int, beta: int, method: str):
            self.rows.append((row["grp"], row["sid"], row["idx"], row["ts_us"], row["val"]))
            self.args = (m, theta, beta, method)

        def terminate(self):
            if not self.rows:
                return
            from alignspark.operators.candidates import expand_block, matrices, numpy_weights
            from alignspark.operators.compose import solve

            m, theta, beta, method = self.args
            p = AlignParams(theta=theta, beta=beta)
            by_grp: dict = {}
            for r in self.rows:
                by_grp.setdefault(r[0], []).append(r)
            for grp, rows in by_grp.items():
                pdf = pd.DataFrame(rows, columns=["grp", "sid", "idx", "ts_us", "val"])
                times, _, has, first = matrices(pdf, m)
                x, lam, spread = expand_block(times, has, m, theta, beta, first, first + len(times) - 1, first)
                _, _, w_fp = numpy_weights(x, lam, p)
                for pos, k in enumerate(sorted(solve(x, w_fp, p, method, spread)), 1):
                    yield grp, pos, [int(v) for v in x[k]], int(w_fp[k])

    spark.udtf.register("align_series", AlignSeries)
