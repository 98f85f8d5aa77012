"""Normal forms and spectra of whole relations."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions.transforms import SpectralTransform
from cadenza.model import TINY, SeriesRelation


def normalize(r: SeriesRelation, ddof: int = 0) -> SeriesRelation:
    """Each series less its mean, over its standard deviation; mean and sd become columns. Constant series are left out (see rejected())."""
    form = r.df.select("series_id", "n", A.normal_form(F.col("values"), ddof).alias("form"), *r.attrs).where(F.col("form.sd") >= TINY)
    return SeriesRelation(form.select("series_id", "n", "form.values", "form.mean", "form.sd", *r.attrs), r.n, r.attrs)


def rejected(r: SeriesRelation) -> DataFrame:
    """Series without a normal form."""
    return r.df.select("series_id").join(normalize(r).df.select("series_id"), "series_id", "left_anti")


def restore(normal: SeriesRelation) -> SeriesRelation:
    values = A.let(F.struct("mean", "sd", "values"), lambda t: F.transform(t["values"], lambda x: x * t["sd"] + t["mean"]))
    return SeriesRelation(normal.df.select("series_id", "n", values.alias("values"), *normal.attrs), normal.n, normal.attrs)


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


def _rows(m: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(0, m.size + 1, m.shape[1]), pa.int32()), pa.array(np.ascontiguousarray(m).ravel()))


def dft(r: SeriesRelation, *carry: str) -> DataFrame:
    """series_id, re and im (coefficients 0 to n // 2 of the unitary transform; the rest are their mirror images), then the columns in carry. Whole batches at a time; there is no shuffle."""
    n, kinds = r.n, dict(r.df.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.fft.rfft(_matrix(batch.column(1), n), axis=1, norm="ortho")
            yield pa.RecordBatch.from_arrays([batch.column(0), _rows(x.real), _rows(x.imag), *batch.columns[2:]], ["series_id", "re", "im", *carry])

    schema = ", ".join(["series_id bigint, re array<double>, im array<double>", *(f"`{c}` {kinds[c]}" for c in carry)])
    return r.df.select("series_id", "values", *carry).mapInArrow(run, schema)


def normal_dft(r: SeriesRelation) -> DataFrame:
    """Spectra of normal forms: series_id, re, im, mean, sd and the attributes, without constant series. Each series is read once and normalised in the batch it comes in."""
    n, attrs, kinds = r.n, r.attrs, dict(r.df.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column(1), n)
            mean, sd = x.mean(axis=1), x.std(axis=1)
            sound = sd >= TINY
            batch, x, mean, sd = batch.filter(pa.array(sound)), x[sound], mean[sound], sd[sound]
            c = np.fft.rfft((x - mean[:, None]) / sd[:, None], axis=1, norm="ortho")
            yield pa.RecordBatch.from_arrays([batch.column(0), _rows(c.real), _rows(c.imag), pa.array(mean), pa.array(sd), *batch.columns[2:]], ["series_id", "re", "im", "mean", "sd", *attrs])

    schema = ", ".join(["series_id bigint, re array<double>, im array<double>, mean double, sd double", *(f"`{c}` {kinds[c]}" for c in r.attrs)])
    return r.df.select("series_id", "values", *r.attrs).mapInArrow(run, schema)


def idft(spectra: DataFrame, n: int) -> DataFrame:
    """series_id and values from series_id, re, im."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column(1), n // 2 + 1) + 1j * _matrix(batch.column(2), n // 2 + 1)
            yield pa.RecordBatch.from_arrays([batch.column(0), _rows(np.fft.irfft(x, n, axis=1, norm="ortho"))], ["series_id", "values"])

    return spectra.select("series_id", "re", "im").mapInArrow(run, "series_id bigint, values array<double>")


def half(t: SpectralTransform) -> tuple[np.ndarray, np.ndarray]:
    """a and b for the coefficients kept of real series."""
    if not t.keeps_real:
        raise ValueError(f"{t.name} makes real series complex")
    return t.a[: t.n_out // 2 + 1], t.b[: t.n_out // 2 + 1]


def _unfolded(spectra: DataFrame, n: int, n_out: int) -> DataFrame:
    """Coefficient f mod n for f up to n_out // 2, the mirror images filled in."""
    if n_out == n:
        return spectra
    at = np.arange(n_out // 2 + 1) % n
    mirrored = at > n // 2
    source, sign = np.where(mirrored, n - at, at), np.where(mirrored, -1.0, 1.0)
    pick = F.expr("array(" + ",".join(map(str, source)) + ")")
    picked = lambda c: A.let(F.col(c), lambda v: F.transform(pick, lambda i: F.get(v, i)))
    return spectra.withColumns({"re": picked("re"), "im": F.zip_with(picked("im"), A.literal(sign), lambda x, s: x * s)})


def transformed(spectra: DataFrame, n: int, t: SpectralTransform) -> DataFrame:
    """Spectra (re, im) after t; other columns stay. Coefficients are multiplied where the rows lie."""
    a, b = half(t)
    re, im = A.times(F.col("re"), F.col("im"), a, b)
    return _unfolded(spectra, n, t.n_out).withColumns({"re": re, "im": im})


def apply(r: SeriesRelation, t: SpectralTransform) -> SeriesRelation:
    """T of a relation, back in the time domain."""
    values = idft(transformed(dft(r), r.n, t), t.n_out)
    return SeriesRelation(values.select("series_id", F.lit(t.n_out).alias("n"), "values"), t.n_out)
