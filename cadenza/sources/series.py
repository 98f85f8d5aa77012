"""Series built from the given tables, and readers and writers of series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cadenza.functions.arrays import cumulated, let, mean
from cadenza.model import SERIES_LONG, SeriesRelation

FIRST_DAY = "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _bucket(date: str, n: int, days: int) -> Column:
    return F.floor(F.datediff(F.col(date).cast("date"), F.lit(FIRST_DAY).cast("date")) * n / F.lit(days)).cast("int")


def _spread(sums: DataFrame, n: int, keys: tuple[str, ...]) -> DataFrame:
    """One array of n values for each key from rows (keys, pos, value), 0 where there is none."""
    held = sums.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("pos", "value"))).alias("at"))
    return held.select(*keys, F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.try_element_at("at", i), F.lit(0.0))).alias("values"))


def supplier_level(spark: SparkSession, sf_dir: str, n: int = 128, days: int = 2500) -> SeriesRelation:
    """Quantities shipped by each supplier in n buckets of time."""
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("series_id"), _bucket("l_shipdate", n, days).alias("pos"), "l_quantity").where(F.col("pos").between(0, n - 1))
    sums = rows.groupBy("series_id", "pos").agg(F.sum("l_quantity").alias("value"))
    return SeriesRelation(_spread(sums, n, ("series_id",)).select("series_id", F.lit(n).alias("n"), "values"), n)


def supplier_walk(spark: SparkSession, sf_dir: str) -> SeriesRelation:
    """Levels less their mean, cumulated: moves like a price."""
    level = supplier_level(spark, sf_dir)
    centred = let(F.col("values"), lambda v: let(mean(v), lambda m: F.transform(v, lambda x: x - m)))
    return SeriesRelation(level.df.withColumn("values", cumulated(centred)), level.n)


def embedding_level(spark: SparkSession, sf_dir: str, n: int = 64) -> SeriesRelation:
    rows = table(spark, sf_dir, "embeddings").where(F.size("embedding") == n)
    return SeriesRelation(rows.select(F.col("vec_id").alias("series_id"), F.lit(n).alias("n"), F.col("embedding").cast("array<double>").alias("values")), n)


def embedding_walk(spark: SparkSession, sf_dir: str) -> SeriesRelation:
    level = embedding_level(spark, sf_dir)
    return SeriesRelation(level.df.withColumn("values", cumulated(F.col("values"))), level.n)


def _micros(ts: str) -> Column:
    """Microseconds of a time without zone, whatever the session's zone is."""
    c = F.col(ts)
    minutes = (F.datediff(c.cast("date"), F.lit("1970-01-01").cast("date")).cast("long") * 24 + F.hour(c)) * 60 + F.minute(c)
    return minutes * 60_000_000 + (F.expr(f"extract(SECOND FROM {ts})") * 1_000_000).cast("long")


def event_walk(spark: SparkSession, sf_dir: str, n: int = 32) -> SeriesRelation:
    """Each user's whole span of time in n equal parts: the mean value of a part's events less 50 (0 without events), cumulated."""
    rows = table(spark, sf_dir, "events").select(F.col("user_id").alias("series_id"), _micros("ts").alias("at"), "value").where("series_id is not null and at is not null and value is not null")
    spans = rows.groupBy("series_id").agg(F.min("at").alias("first"), F.max("at").alias("last"))
    placed = rows.join(spans, "series_id").select("series_id", F.expr(f"cast(((at - first) * {n}) div (last - first + 1) as int)").alias("pos"), "value")
    means = placed.groupBy("series_id", "pos").agg((F.avg("value") - 50).alias("value"))
    relation = _spread(means, n, ("series_id",))
    return SeriesRelation(relation.select("series_id", F.lit(n).alias("n"), cumulated(F.col("values")).alias("values")), n)


def segment_sales(spark: SparkSession, sf_dir: str, n: int = 32, days: int = 2405) -> SeriesRelation:
    """Order totals by nation, market segment and priority; ids count these in the order of their names."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_totalprice", "o_orderpriority", _bucket("o_orderdate", n, days).alias("pos")).where(F.col("pos").between(0, n - 1))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    region = table(spark, sf_dir, "region").select("r_regionkey", "r_name")
    places = nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    joined = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    keys = ("region", "nation", "segment", "priority")
    named = joined.select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"), F.col("o_orderpriority").alias("priority"), "pos", F.col("o_totalprice").cast("decimal(18,2)").alias("price"))
    sums = named.groupBy(*keys, "pos").agg(F.sum("price").cast("double").alias("value"))
    # at most nations x segments x priorities rows: an order over all of them is small
    numbered = _spread(sums, n, keys).withColumn("series_id", F.row_number().over(Window.orderBy("nation", "segment", "priority")).cast("long"))
    return SeriesRelation(numbered.select("series_id", F.lit(n).alias("n"), "values", *keys), n, keys)


def doc_wordlen(spark: SparkSession, sf_dir: str, n: int = 128) -> SeriesRelation:
    """Each document's words in n equal parts, mean word lengths: whole texts, those of fewer words than parts stretched. Documents without words have none."""
    lengths = F.transform(F.filter(F.split("text", r"[ \t\n\r]+"), lambda w: w != ""), F.length)

    def parts(ws: Column) -> Column:
        first = lambda k: F.floor(k.cast("long") * F.size(ws) / F.lit(n)).cast("int")
        many = lambda k: F.greatest(first(k + 1) - first(k), F.lit(1))
        return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: F.aggregate(F.slice(ws, first(k) + 1, many(k)), F.lit(0).cast("long"), lambda a, x: a + x) / many(k))

    worded = table(spark, sf_dir, "documents").where(F.col("text").rlike(r"[^ \t\n\r]"))
    return SeriesRelation(worded.select(F.col("doc_id").alias("series_id"), F.lit(n).alias("n"), let(lengths, parts).alias("values")), n)


def random_walk(spark: SparkSession, sf_dir: str, n: int = 128, count: int = 1000) -> SeriesRelation:
    """Steps uniform in [-4, 4), start normal (mean 50, deviation 15, within 0 and 100), all from md5 of the part key and place."""
    unit = lambda key: F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("double") / 4294967296.0
    key = F.col("series_id").cast("string")
    keys = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("series_id")).orderBy("series_id").limit(count)
    start = 50 + 15 * F.sqrt(-2 * F.log(unit(F.concat(key, F.lit("-u"))) + 1e-12)) * F.cos(2 * F.pi() * unit(F.concat(key, F.lit("-v"))))
    steps = F.transform(F.sequence(F.lit(1), F.lit(n - 1)), lambda i: unit(F.concat(key, F.lit("-"), i.cast("string"))) * 8 - 4)
    first = F.array(F.least(F.greatest(start, F.lit(0.0)), F.lit(100.0)))
    # of two steps each value is the last one's, so sums run in order
    values = F.aggregate("steps", first, lambda a, s: F.concat(a, F.array(F.element_at(a, -1) + s)))
    return SeriesRelation(keys.withColumn("steps", steps).select("series_id", F.lit(n).alias("n"), values.alias("values")), n)


RELATIONS = {"supplier_walk": supplier_walk, "supplier_level": supplier_level, "embedding_walk": embedding_walk, "embedding_level": embedding_level, "event_walk": event_walk, "segment_sales": segment_sales, "doc_wordlen": doc_wordlen, "random_walk": random_walk}


def read_long(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """Long-form series from parquet, orc, csv or json files, with the declared schema (nothing is inferred)."""
    return spark.read.format(kind).schema(SERIES_LONG).options(**options).load(path)


def write_series(relation: SeriesRelation, path: str, partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    writer = relation.df.write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def write_bucketed(relation: SeriesRelation, name: str, buckets: int) -> None:
    """A table bucketed by series, so joins on series_id need no shuffle."""
    relation.df.write.mode("overwrite").bucketBy(buckets, "series_id").sortBy("series_id").saveAsTable(name)
