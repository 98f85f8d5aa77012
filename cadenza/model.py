"""Relations of series.

Long form: series_id BIGINT, pos INT, value DOUBLE. Array form: series_id BIGINT, n INT,
values ARRAY<DOUBLE>, then attributes. All series of a relation have one length.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

SERIES_LONG = T.StructType([T.StructField("series_id", T.LongType()), T.StructField("pos", T.IntegerType()), T.StructField("value", T.DoubleType())])
#: Standard deviations and magnitudes below this count as 0.
TINY = 1e-9
#: Added to bounds of tests that may only over-select.
SLACK = 1e-9


@dataclass(frozen=True)
class SeriesRelation:
    """Series of length n in array form; attrs are further columns that travel with them."""

    df: DataFrame
    n: int
    attrs: tuple[str, ...] = ()

    @staticmethod
    def from_long(long: DataFrame, n: int, attrs: tuple[str, ...] = ()) -> SeriesRelation:
        """One shuffle by series. Series with a missing, null or NaN position are left out (see rejected())."""
        gathered = long.groupBy("series_id", *attrs).agg(F.array_sort(F.collect_list(F.struct("pos", "value"))).alias("points"))
        values = F.transform("points", lambda p: p["value"])
        whole = (F.size("points") == n) & F.forall("points", lambda p: p["value"].isNotNull() & ~F.isnan(p["value"]))
        return SeriesRelation(gathered.where(whole).select("series_id", F.lit(n).alias("n"), values.alias("values"), *attrs), n, attrs)

    def long(self) -> DataFrame:
        return self.df.select("series_id", F.posexplode("values").alias("pos", "value"))

    def where(self, condition) -> SeriesRelation:
        """The part of the relation that a pattern expression denotes."""
        return SeriesRelation(self.df.where(condition), self.n, self.attrs)

    def one(self, series_id: int) -> list[float]:
        row = self.df.where(F.col("series_id") == series_id).select("values").first()
        if row is None:
            raise KeyError(f"no series {series_id}")
        return list(row["values"])


def check_length(have: int, want: int) -> None:
    if have != want:
        raise ValueError(f"a series of length {have} where {want} is needed")
