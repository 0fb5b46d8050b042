"""Fast transforms along the first axis, and array expressions that stay in the JVM."""

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def fwht(x: np.ndarray) -> np.ndarray:
    """Walsh-Hadamard transform (Sylvester order, unscaled) of a power-of-two number of rows, in O(N log N)."""
    n = len(x)
    if n & (n - 1):
        raise ValueError("the number of rows must be a power of two")
    out, half = np.array(x, float), 1
    while half < n:
        pairs = out.reshape(n // (2 * half), 2, half, *out.shape[1:])
        out = np.stack([pairs[:, 0] + pairs[:, 1], pairs[:, 0] - pairs[:, 1]], 1).reshape(out.shape)
        half *= 2
    return out


def haar(x: np.ndarray) -> np.ndarray:
    """Orthonormal Haar transform of a power-of-two number of rows: averages first, then ever finer differences."""
    low, fine = np.array(x, float), []
    while len(low) > 1:
        fine.append((low[0::2] - low[1::2]) / np.sqrt(2))
        low = (low[0::2] + low[1::2]) / np.sqrt(2)
    return np.concatenate([low, *fine[::-1]])


def hadamard_sign(i: Column, j: Column) -> Column:
    return F.lit(1) - 2 * (F.bit_count(i.bitwiseAND(j)) % 2)


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def axpy(alpha, x: Column | str, y: Column | str) -> Column:
    return F.zip_with(x, y, lambda u, v: F.lit(alpha) * u + v)


def soft_threshold(v: Column | str, tau) -> Column:
    v = F.col(v) if isinstance(v, str) else v
    return F.signum(v) * F.greatest(F.abs(v) - F.lit(tau), F.lit(0.0))


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def logloss(margin: Column) -> Column:
    """log(1 + e^-m) without overflow."""
    return F.greatest(-margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin)))


def register(spark) -> None:
    """The transforms as SQL functions on ARRAY<DOUBLE>: erasure_fwht, erasure_haar, erasure_dft; and row tables."""
    from pyspark.sql.functions import pandas_udf, udtf

    def over(f):
        def call(column: pd.Series) -> pd.Series:
            return pd.Series([f(np.asarray(v, float)).tolist() for v in column])

        return pandas_udf(call, "array<double>")

    def dft(v: np.ndarray) -> np.ndarray:
        z = np.fft.fft(v) / np.sqrt(len(v))
        return np.stack([z.real, z.imag], 1).ravel()

    for name, f in (("erasure_fwht", fwht), ("erasure_haar", haar), ("erasure_dft", dft)):
        spark.udf.register(name, over(f))

    from erasureml.operators import codes

    def table(build):
        class Rows:
            def eval(self, size: int):
                code = build(size)
                for i in range(code.N):
                    row = code.rows(i, i + 1)[0]
                    for j in np.flatnonzero(row).tolist():
                        yield i, j, float(row[j])

        return udtf(Rows, returnType="enc_row: bigint, src_row: bigint, coef: double")

    spark.udtf.register("hadamard_rows", table(codes.hadamard_full))
    spark.udtf.register("steiner_rows", table(codes.steiner))
    spark.udtf.register("paley_rows", table(codes.paley))
    spark.udtf.register("haar_rows", table(codes.haar_full))


def vec_sum():
    """Grouped aggregate: the element-wise sum of arrays of one length."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("array<double>")
    def total(v: pd.Series) -> list:
        return np.sum([np.asarray(x, float) for x in v], axis=0).tolist()

    return total


def gram():
    """Grouped aggregate: the inner products of the columns of arrays, row by row."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("array<double>")
    def products(v: pd.Series) -> list:
        x = np.stack([np.asarray(r, float) for r in v])
        return (x.T @ x).ravel().tolist()

    return products
