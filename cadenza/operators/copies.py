"""Copies: series that agree in every value. Joins compare one of each class and name the rest, as m copies would else be m squared pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.model import SeriesRelation
from cadenza.operators.kindex import KIndex
from cadenza.storage import keep


def members(r: SeriesRelation) -> DataFrame:
    """(series_id, class_id) of all series, computed once: class_id is the least id of those with the same values. Digests of values are shuffled, not values."""
    # adding 0 makes the two zeros one
    exact = F.transform("values", lambda x: (x + F.lit(0.0)).cast("string"))
    keyed = r.df.select("series_id", F.unhex(F.md5(F.concat_ws(",", exact))).alias("key"))
    least = keyed.groupBy("key").agg(F.min("series_id").alias("class_id"))
    return keep(keyed.join(least, "key").select("series_id", "class_id"))


def few(r: SeriesRelation, of: DataFrame, count: int) -> SeriesRelation:
    """The one or two series with the least ids of each class (of: its members)."""
    ids = of.where("series_id = class_id").select("series_id")
    if count == 2:
        ids = ids.union(of.where("series_id <> class_id").groupBy("class_id").agg(F.min("series_id").alias("series_id")).select("series_id"))
    return SeriesRelation(r.df.join(ids, "series_id", "left_semi"), r.n, r.attrs)


def indexed(index: KIndex | DataFrame, of: DataFrame) -> DataFrame:
    """Members of the classes whose representative is in an index, or among some spectra (constant series aren't)."""
    held = index.features if isinstance(index, KIndex) else index
    return of.join(held.select(F.col("series_id").alias("class_id")), "class_id", "left_semi")


def copies(index: KIndex | DataFrame, of: DataFrame) -> DataFrame:
    """(id_l, id_r): a class of the index and each of its further members."""
    return indexed(index, of).where("series_id <> class_id").select(F.col("class_id").alias("id_l"), F.col("series_id").alias("id_r"))


def answers(index: KIndex, of: DataFrame, links: DataFrame, ordered: bool) -> int:
    """How many pairs of series the links between classes and the classes themselves stand for; none is made for that."""
    sizes = keep(indexed(index, of).groupBy("class_id").agg(F.count(F.lit(1)).alias("n")))
    between = links.join(sizes.select(F.col("class_id").alias("id_l"), F.col("n").alias("n_l")), "id_l").join(sizes.select(F.col("class_id").alias("id_r"), F.col("n").alias("n_r")), "id_r")
    outer = between.agg(F.coalesce(F.sum(F.col("n_l") * F.col("n_r")), F.lit(0).cast("long")).alias("n")).first().n
    inner = sizes.agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1)), F.lit(0).cast("long")).alias("n")).first().n
    return outer + (inner if ordered else inner // 2)
