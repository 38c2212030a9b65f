"""Functions and table functions for SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spectrack.functions import numbers as N
from spectrack.functions import track as K
from spectrack.functions.spectral import dct, idct
from spectrack.operators import blocks as B


def varint_bits(u: pd.Series, l: pd.Series) -> pd.Series:  # noqa: E741
    """Bits of non-negative integers with chunks of l bits."""
    length = N.bit_length(u.to_numpy(np.int64))
    chunk = l.to_numpy(np.int64)
    return pd.Series(-(-length // chunk) * (chunk + 1))


def zz1(n: pd.Series) -> pd.Series:
    return pd.Series(N.zigzag1(n.to_numpy(np.int64)))


def dct_block(v: pd.Series) -> pd.Series:
    return v.map(lambda x: None if x is None or not len(x) else dct(np.asarray(x, float))[0])


def idct_block(c: pd.Series) -> pd.Series:
    return c.map(lambda x: None if x is None or not len(x) else idct(np.asarray(x, float), len(x))[0])


class DecodeTrack:
    """(t, pos) of each sample of a uniform track's container."""

    def eval(self, payload: bytes, first: int):
        e, p = K.unpack(bytes(payload))
        if not e.uniform:
            raise ValueError("only uniform tracks imply their times; use decompress with a clock")
        t = first + e.dt * np.arange(int(e.counts[0]))
        for when, x in zip(t.tolist(), K.decode(e, t, p).tolist(), strict=True):
            yield when, x


def sed_stats(sed: pd.Series) -> list[float]:
    """Number, maximum and mean of a group's errors."""
    return [float(len(sed)), float(sed.max()), float(sed.mean())]


def register(spark: SparkSession) -> None:
    for f, kind in ((varint_bits, "long"), (zz1, "long"), (dct_block, "array<double>"), (idct_block, "array<double>")):
        spark.udf.register(f.__name__, F.pandas_udf(f, kind))
    spark.udf.register("sed_stats", F.pandas_udf(sed_stats, "array<double>", F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("decode_track", F.udtf(DecodeTrack, returnType="t long, pos array<double>"))


def views(points: DataFrame, container: DataFrame, b_s: int, step: int) -> None:
    """Named views of uniform points: `points`, their velocities by block (`blocks`), and `container`."""
    points.createOrReplaceTempView("points")
    B.velocities(B.axes(B.from_clock(points, step)), b_s).createOrReplaceTempView("blocks")
    container.createOrReplaceTempView("container")
