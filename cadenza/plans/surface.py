"""Operators around the series methods: filling, summaries, ranks, frames, set operations, nested data, functions for SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cadenza.functions import transforms as T
from cadenza.operators import copies, joins
from cadenza.plans.workloads import classes_of, index_of, r4
from cadenza.sources.series import event_walk, segment_sales, table
from cadenza.storage import keep

#: (name, parameters, body) of functions for SQL over arrays of doubles.
SQL_FUNCTIONS = [
    ("series_distance", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"),
    ("series_reverse", "a ARRAY<DOUBLE>", "transform(a, x -> -x)"),
    ("series_stretch", "a ARRAY<DOUBLE>, m INT", "flatten(transform(a, x -> array_repeat(x, m)))"),
    ("series_mavg", "a ARRAY<DOUBLE>, m INT", "transform(a, (x, i) -> aggregate(sequence(0, m - 1), 0D, (s, j) -> s + get(a, pmod(i - j, size(a)))) / m)"),
    ("series_mean", "a ARRAY<DOUBLE>", "aggregate(a, 0D, (s, x) -> s + x) / size(a)"),
    ("series_dft_re", "a ARRAY<DOUBLE>, f INT", "aggregate(transform(a, (x, i) -> x * cos(2 * pi() * f * i / size(a))), 0D, (s, x) -> s + x) / sqrt(size(a))"),
    ("series_dft_im", "a ARRAY<DOUBLE>, f INT", "-aggregate(transform(a, (x, i) -> x * sin(2 * pi() * f * i / size(a))), 0D, (s, x) -> s + x) / sqrt(size(a))"),
]


def register(spark: SparkSession) -> None:
    """Temporary SQL functions, which the optimizer inlines; the UDTF series_spine; and series_agg(pos, value)."""
    for name, parameters, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURN {body}")

    @F.udtf(returnType="pos int")
    class SeriesSpine:
        """Positions 0 to n - 1."""

        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    spark.udtf.register("series_spine", SeriesSpine)


def series_agg(pos: str, value: str):
    """Values in the order of their positions, as an array."""
    return F.transform(F.array_sort(F.collect_list(F.struct(pos, value))), lambda p: p[value])


def asof_fill(spark, sf_dir):
    """Each user's last value at or before each of twelve grid times of their own span, an hour of which is one twelfth."""
    e = table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "value")
    span = e.groupBy("user_id").agg(F.min("ts").alias("first"), F.max("ts").alias("last"))
    step = (F.unix_micros("last") - F.unix_micros("first")) / 12
    grid = span.select("user_id", F.explode(F.sequence(F.lit(0), F.lit(12))).alias("slot"), (F.unix_micros("first")).alias("a"), step.alias("step"))
    grid = grid.select("user_id", "slot", F.floor(F.col("a") + F.col("slot") * F.col("step")).alias("at"), F.lit(None).cast("double").alias("value"), F.lit(1 << 62).cast("long").alias("event_id"))
    both = grid.unionByName(e.select("user_id", F.lit(None).cast("int").alias("slot"), F.unix_micros("ts").alias("at"), "value", "event_id"))
    last = F.last("value", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("at", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("filled", last).where("slot is not null").select("user_id", "slot", r4(F.col("filled")).alias("value"))


def _sales(spark, sf_dir) -> DataFrame:
    r = segment_sales(spark, sf_dir).df
    return r.select("region", "segment", "priority", "series_id", F.aggregate("values", F.lit(0.0), lambda a, x: a + x).alias("total"))


def cube(spark, sf_dir):
    return _sales(spark, sf_dir).cube("region", "segment").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("total"), 0).alias("total"))


def rollup(spark, sf_dir):
    return _sales(spark, sf_dir).rollup("region", "segment").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("total"), 2).alias("top"))


def grouping_sets(spark, sf_dir):
    s = _sales(spark, sf_dir)
    return s.groupingSets([["region"], ["priority"], []], "region", "priority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("g"))


def rank_windows(spark, sf_dir):
    w = Window.partitionBy("region").orderBy("rounded", "series_id")
    s = _sales(spark, sf_dir).withColumn("rounded", F.round("total", 2))
    return s.select("series_id", F.row_number().over(w).alias("nth"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(w).alias("quarter"), r4(F.percent_rank().over(w)).alias("share"), r4(F.cume_dist().over(w)).alias("upto"), r4(F.lag("rounded", 1, 0.0).over(w)).alias("before"), r4(F.lead("rounded", 1, 0.0).over(w)).alias("after"))


def range_frame(spark, sf_dir):
    """Each order's customer's spending over the seven days up to it."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("day"), F.col("o_totalprice").cast("decimal(18,2)").alias("price"))
    w = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-7, 0)
    return o.select("o_orderkey", "day", F.sum("price").over(w).cast("double").alias("week"))


def topk(spark, sf_dir):
    return _sales(spark, sf_dir).select("series_id", F.round("total", 2).alias("total")).orderBy(F.desc("total"), "series_id").limit(15)


def _answers(spark, sf_dir):
    """Links between classes of copies, smoothed and not, and each class's further members."""
    ix = index_of(spark, sf_dir, "supplier_walk", 1)
    smooth = joins.self_join(ix, T.moving_average(ix.n, 20), 5.0).select("id_l", "id_r")
    return smooth, joins.self_join(ix, None, 6.0).select("id_l", "id_r"), copies.copies(ix, classes_of(spark, sf_dir, "supplier_walk"))


def setops(spark, sf_dir):
    """Pairs of classes by whether smoothing, no smoothing or both find them, and copies, which both find."""
    a, b, same = _answers(spark, sf_dir)
    parts = {"both": a.intersect(b), "smoothed only": a.exceptAll(b), "plain only": b.exceptAll(a), "copy": same}
    out = None
    for k, df in parts.items():
        part = df.withColumn("kind", F.lit(k))
        out = part if out is None else out.unionByName(part)
    return out


def semi_anti(spark, sf_dir):
    """Suppliers with and without a partner: a class has one if it is linked, and so has each member of one with copies."""
    a, _, same = _answers(spark, sf_dir)
    linked = a.select(F.col("id_l").alias("class_id")).union(a.select("id_r")).union(same.select("id_l")).distinct()
    ids = keep(classes_of(spark, sf_dir, "supplier_walk").join(linked, "class_id", "left_semi").select("series_id"))
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("series_id"))
    return s.join(ids, "series_id", "left_semi").withColumn("partner", F.lit(True)).unionByName(s.join(ids, "series_id", "left_anti").withColumn("partner", F.lit(False)))


def interval_join(spark, sf_dir):
    """Events of one user within an hour after another event of theirs: by hour bins, then exactly."""
    e = table(spark, sf_dir, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    hour = 3_600_000_000
    left = e.select("user_id", F.col("event_id").alias("a"), F.col("at").alias("from"), F.explode(F.array(F.floor(F.col("at") / hour), F.floor(F.col("at") / hour) + 1)).alias("bin"))
    right = e.select("user_id", F.col("event_id").alias("b"), "at", F.floor(F.col("at") / hour).alias("bin"))
    return left.join(right, ["user_id", "bin"]).where(F.expr(f"at > from and at <= from + {hour}")).select("a", "b")


def range_join(spark, sf_dir):
    """Customers into bands of account balance, by bins and an exact test."""
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    bands = spark.createDataFrame([(i, -1000.0 + 550 * i, -1000.0 + 550 * i + 700) for i in range(20)], "band int, low double, high double")
    binned = bands.withColumn("bin", F.explode(F.sequence(F.floor(F.col("low") / 500).cast("int"), F.floor(F.col("high") / 500).cast("int"))))
    return c.withColumn("bin", F.floor(F.col("c_acctbal") / 500).cast("int")).join(F.broadcast(binned), "bin").where("c_acctbal >= low and c_acctbal < high").groupBy("band").agg(F.count(F.lit(1)).alias("n"))


def json_values(spark, sf_dir):
    """The second value that events carry in their properties."""
    e = table(spark, sf_dir, "events")
    return e.select("event_type", F.from_json("props", "k int").getField("k").alias("k"), F.get_json_object("props", "$.k").cast("int").alias("same")).groupBy("event_type").agg(F.sum("k").alias("k"), F.sum(F.when(F.col("k") == F.col("same"), 1).otherwise(0)).alias("same"))


def map_attributes(spark, sf_dir):
    s = segment_sales(spark, sf_dir).df
    m = s.select("series_id", F.map_from_arrays(F.array(F.lit("region"), F.lit("segment")), F.array("region", "segment")).alias("attrs"))
    return m.select("series_id", F.element_at("attrs", "region").alias("region"), F.size("attrs").alias("n"), F.concat_ws("|", F.map_values(F.transform_values("attrs", lambda _, v: F.lower(v)))).alias("lowered"))


def strings(spark, sf_dir):
    d = table(spark, sf_dir, "documents")
    return d.select("doc_id", F.length("text").cast("long").alias("n"), F.substring(F.md5("text"), 1, 8).alias("key"), F.upper("lang").alias("lang"), F.length(F.regexp_replace("text", "[a-z]", "")).cast("long").alias("others"))


def dates(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.year("o_orderdate").alias("year"), F.dayofyear("o_orderdate").alias("day"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("since"))


def pivot(spark, sf_dir):
    s = _sales(spark, sf_dir).withColumn("p", F.substring("priority", 1, 1))
    return s.groupBy("region").pivot("p", ["1", "2", "3"]).agg(F.count(F.lit(1))).select("region", *(F.coalesce(F.col(c), F.lit(0)).alias(f"p{c}") for c in "123"))


def approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5).alias("median"))


def sql_functions(spark, sf_dir):
    register(spark)
    event_walk(spark, sf_dir).df.createOrReplaceTempView("cadenza_event_walk")
    return spark.sql("SELECT a.series_id, round(series_distance(a.values, b.values) + 3e-7D, 4) + 0D AS dist, round(series_distance(series_mavg(a.values, 5), series_mavg(b.values, 5)) + 3e-7D, 4) + 0D AS smoothed, round(series_mean(a.values) + 3e-7D, 4) + 0D AS mean, round(series_dft_re(a.values, 1) + 3e-7D, 4) + 0D AS re1, round(series_dft_im(a.values, 1) + 3e-7D, 4) + 0D AS im1, size(series_stretch(a.values, 2)) AS stretched, round(series_reverse(a.values)[3] + 3e-7D, 4) + 0D AS reversed FROM cadenza_event_walk a CROSS JOIN (SELECT values FROM cadenza_event_walk WHERE series_id = 0) b")


def udaf_series(spark, sf_dir):
    """series_agg by built-in functions, and an energy by a grouped pandas aggregate; groups are single series."""
    long = event_walk(spark, sf_dir).long()

    @F.pandas_udf("double")
    def energy_agg(x: pd.Series) -> float:
        return float((x * x).sum())

    whole = long.groupBy("series_id").agg(series_agg("pos", "value").alias("values"))
    energies = long.groupBy("series_id").agg(energy_agg("value").alias("energy"))
    return whole.join(energies, "series_id").select("series_id", F.size("values").alias("n"), r4(F.element_at("values", -1)).alias("last"), F.round("energy", 2).alias("energy"))


def udtf_spine(spark, sf_dir):
    """A row for each of a user's events' places, and how many of these are left."""
    register(spark)
    table(spark, sf_dir, "events").groupBy("user_id").agg(F.count("event_id").cast("int").alias("n")).createOrReplaceTempView("cadenza_event_counts")
    return spark.sql("SELECT user_id, pos, n - pos - 1 AS remaining FROM cadenza_event_counts, LATERAL series_spine(n)")


def udf_fft(spark, sf_dir):
    """Magnitude of coefficient 1 by a vectorised function."""
    @F.pandas_udf("double")
    def size_of_first(values: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for v in values:
            yield pd.Series(np.abs(np.fft.rfft(np.stack(v.to_numpy()), axis=1, norm="ortho")[:, 1]) if len(v) else [], dtype=float)

    # kept first: the optimizer else folds the function into the aggregation that makes the arrays, where it can't run
    return keep(event_walk(spark, sf_dir).df).select("series_id", r4(size_of_first("values")).alias("m1"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    surface = {"asof_fill": asof_fill, "cube": cube, "rollup": rollup, "grouping_sets": grouping_sets, "rank_windows": rank_windows, "range_frame": range_frame, "topk": topk, "setops": setops, "semi_anti": semi_anti, "interval_join": interval_join, "range_join": range_join, "json": json_values, "map": map_attributes, "strings": strings, "dates": dates, "pivot": pivot, "approx_distinct": approx_distinct}
    return {f"surface_{k}": f for k, f in surface.items()} | {"sql_functions": sql_functions, "udaf_series_agg": udaf_series, "udtf_spine": udtf_spine, "udf_fft": udf_fft}


def oracle_sql() -> dict[str, str]:
    from cadenza.plans import oracles as O

    sales = f"{O.R['segment_sales']}, s AS (SELECT region, segment, priority, series_id, list_sum(v) AS total FROM r)"
    pairs = f"a AS ({O.joined('supplier_walk', 5, [1 / 20] * 20)}), b AS ({O.joined('supplier_walk', 6)})"
    class_pairs = ", ".join(f"{k}0 AS ({q}), {k} AS (SELECT id_l, id_r FROM {k}0 WHERE kind = 'link')" for k, q in (("a", O.class_joined("supplier_walk", 5, [1 / 20] * 20)), ("b", O.class_joined("supplier_walk", 6))))
    walk = O.R["event_walk"]
    rk = O.r4
    return {
        "surface_asof_fill": "WITH e AS (SELECT user_id, epoch_us(ts) AS tm, event_id, value FROM events), g AS (SELECT user_id, slot, CAST(floor(a + slot * step) AS BIGINT) AS tm FROM (SELECT user_id, min(tm) AS a, (max(tm) - min(tm)) / 12 AS step FROM e GROUP BY 1), (SELECT unnest(range(0, 13)) AS slot)), j AS (SELECT g.user_id, slot, arg_max(value, (e.tm, event_id)) AS value FROM g JOIN e ON e.user_id = g.user_id AND e.tm <= g.tm GROUP BY 1, 2) SELECT user_id, CAST(slot AS INT) AS slot, round(value + 3e-7, 4) + 0.0::DOUBLE AS value FROM j",
        "surface_cube": f"WITH {sales} SELECT region, segment, count(*) AS n, round(sum(total), 0) AS total FROM s GROUP BY CUBE (region, segment)",
        "surface_rollup": f"WITH {sales} SELECT region, segment, count(*) AS n, round(max(total), 2) AS top FROM s GROUP BY ROLLUP (region, segment)",
        "surface_grouping_sets": f"WITH {sales} SELECT region, priority, count(*) AS n, CAST(grouping(region, priority) AS BIGINT) AS g FROM s GROUP BY GROUPING SETS ((region), (priority), ())",
        "surface_rank_windows": f"WITH {sales} SELECT series_id, CAST(row_number() OVER w AS INT) AS nth, CAST(dense_rank() OVER w AS INT) AS dense, CAST(ntile(4) OVER w AS INT) AS quarter, {rk('percent_rank() OVER w')} AS share, {rk('cume_dist() OVER w')} AS upto, {rk('lag(rounded, 1, 0.0) OVER w')} AS before, {rk('lead(rounded, 1, 0.0) OVER w')} AS after FROM (SELECT *, round(total, 2) AS rounded FROM s) WINDOW w AS (PARTITION BY region ORDER BY rounded, series_id)",
        "surface_range_frame": "WITH o AS (SELECT o_orderkey, o_custkey, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS day, CAST(o_totalprice AS DECIMAL(18,2)) AS price FROM orders) SELECT o_orderkey, day, CAST(sum(price) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 7 PRECEDING AND CURRENT ROW) AS DOUBLE) AS week FROM o",
        "surface_topk": f"WITH {sales} SELECT series_id, round(total, 2) AS total FROM s ORDER BY 2 DESC, 1 LIMIT 15",
        "surface_setops": f"WITH {class_pairs} SELECT id_l, id_r, 'both' AS kind FROM (SELECT id_l, id_r FROM a INTERSECT SELECT id_l, id_r FROM b) UNION ALL SELECT id_l, id_r, 'smoothed only' FROM (SELECT id_l, id_r FROM a EXCEPT SELECT id_l, id_r FROM b) UNION ALL SELECT id_l, id_r, 'plain only' FROM (SELECT id_l, id_r FROM b EXCEPT SELECT id_l, id_r FROM a) UNION ALL SELECT id_l, id_r, 'copy' FROM a0 WHERE kind = 'copy'",
        "surface_semi_anti": f"WITH {pairs} SELECT s_suppkey AS series_id, s_suppkey IN (SELECT id_l FROM a UNION SELECT id_r FROM a) AS partner FROM supplier",
        "surface_interval_join": "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 1 HOUR",
        "surface_range_join": "SELECT CAST(band AS INT) AS band, count(*) AS n FROM customer, (SELECT unnest(range(0, 20)) AS band) WHERE c_acctbal >= -1000.0 + 550 * band AND c_acctbal < -1000.0 + 550 * band + 700 GROUP BY 1",
        "surface_json": "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS INT)) AS BIGINT) AS k, CAST(count(json_extract_string(props, '$.k')) AS BIGINT) AS same FROM events GROUP BY 1",
        "surface_map": f"WITH {O.R['segment_sales']} SELECT series_id, region, CAST(2 AS INT) AS n, lower(region) || '|' || lower(segment) AS lowered FROM r",
        "surface_strings": "SELECT doc_id, CAST(length(text) AS BIGINT) AS n, substr(md5(text), 1, 8) AS key, upper(lang) AS lang, CAST(length(regexp_replace(text, '[a-z]', '', 'g')) AS BIGINT) AS others FROM documents",
        "surface_dates": "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, CAST(year(o_orderdate) AS INT) AS year, CAST(dayofyear(o_orderdate) AS INT) AS day, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS since FROM orders",
        "surface_pivot": f"WITH {sales} SELECT region, " + ", ".join(f"count(*) FILTER (substr(priority, 1, 1) = '{c}') AS p{c}" for c in "123") + " FROM s GROUP BY 1",
        "sql_functions": f"WITH {walk} SELECT a.series_id, {rk('list_distance(a.v, b.v)')} AS dist, {rk(f'list_distance({O.conv('a.v', [1 / 5] * 5)}, {O.conv('b.v', [1 / 5] * 5)})')} AS smoothed, {rk('list_avg(a.v)')} AS mean, {rk(O._dft('a.v', 32, '1', 'cos'))} AS re1, {rk(O._dft('a.v', 32, '1', 'sin'))} AS im1, CAST(64 AS INT) AS stretched, {rk('-a.v[4]')} AS reversed FROM r a, r b WHERE b.series_id = 0",
        "udaf_series_agg": f"WITH {walk} SELECT series_id, CAST(len(v) AS INT) AS n, {rk('v[32]')} AS last, round(list_sum(list_transform(v, lambda x: x * x)), 2) AS energy FROM r",
        "udtf_spine": "SELECT user_id, CAST(pos AS INT) AS pos, CAST(n - pos - 1 AS INT) AS remaining FROM (SELECT user_id, count(event_id) AS n FROM events GROUP BY 1), LATERAL (SELECT unnest(range(0, n)) AS pos)",
        "udf_fft": f"WITH {walk} SELECT series_id, {rk(f'sqrt(power({O._dft('v', 32, '1', 'cos')}, 2) + power({O._dft('v', 32, '1', 'sin')}, 2))')} AS m1 FROM r",
    }
