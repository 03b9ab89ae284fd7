"""Column expressions and UDFs of the engine: bounds on boxes, spectra and normalisation on arrays, grouped aggregates."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from . import kernels as K


def box_min_dist2(lo: Column, hi: Column, y: Column) -> Column:
    """Squared distance of a point to a box, arrays of equal length."""
    g = F.zip_with(F.arrays_zip(lo.alias("lo"), hi.alias("hi")), y, lambda b, v: F.greatest(b["lo"] - v, v - b["hi"], F.lit(0.0)))
    return F.aggregate(g, F.lit(0.0), lambda s, x: s + x * x)


def pivot_gap2(plo: Column, phi: Column, p: Column) -> Column:
    """Squared gap between a pivot distance and an interval of them."""
    g = F.greatest(plo - p, p - phi, F.lit(0.0))
    return g * g


def relative_contrast(d2: Column) -> Column:
    """Farthest over nearest distance of a group; null if the nearest is 0."""
    return F.try_divide(F.sqrt(F.max(d2)), F.sqrt(F.min(d2)))


def dft_bin(values: Column, b: int) -> Column:
    """Struct (re, im) of one bin of an array's spectrum."""
    n = F.size(values)
    part = lambda f, sign: F.aggregate(F.transform(values, lambda v, j: v * f(F.lit(2 * np.pi * b) * j / n) * sign), F.lit(0.0), lambda s, x: s + x)
    return F.struct(part(F.cos, 1).alias("re"), part(F.sin, -1).alias("im"))


@F.pandas_udf(ArrayType(DoubleType()))
def znorm_udf(values: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """Normalised array (population deviation); constant arrays become zeros."""
    for s in values:
        yield s.map(lambda v: None if v is None else K.znorm(np.asarray(v, float)))


@F.pandas_udf(ArrayType(DoubleType()))
def rfft_udf(values: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """One-sided spectrum as re, im, re, im, ..."""
    for s in values:
        yield s.map(lambda v: None if v is None else np.fft.rfft(np.asarray(v, float)).view(float))


@F.pandas_udf(ArrayType(DoubleType()))
def idft_udf(spectrum: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
    """Values of a given length from an interleaved one-sided spectrum."""
    for s, n in spectrum:
        yield pd.Series([np.fft.irfft(np.ascontiguousarray(v, float).view(complex), int(k)) for v, k in zip(s, n, strict=True)])


def box_agg(lo: str, hi: str, d: int) -> list[Column]:
    """Box of a group as native aggregates of the arrays' positions."""
    return [F.array(*[F.min(F.get(lo, F.lit(i))) for i in range(d)]).alias("lo"), F.array(*[F.max(F.get(hi, F.lit(i))) for i in range(d)]).alias("hi")]


def topk_agg(value: Column, k: int) -> Column:
    """The k smallest of a group, for small groups and k."""
    return F.slice(F.array_sort(F.collect_list(value)), 1, k)
