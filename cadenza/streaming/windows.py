"""Series that arrive as a stream of events."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from cadenza.functions.arrays import euclid
from cadenza.storage import shared_folder

#: Coefficients kept of each user's last WINDOW values.
WINDOW = 32
KEPT = (1, 2)
#: Arrivals after which coefficients are computed anew, so rounding can't build up.
REFRESH = 256


def events(spark: SparkSession, sf_dir: str, lateness: str = "1 hour") -> DataFrame:
    """The events table as a file stream; its zoneless times become timestamps, which watermarks need."""
    path = f"{sf_dir}/events.parquet"
    table = spark.read.parquet(path)
    reader = spark.readStream.schema(table.schema)
    if [f.rstrip("/").rpartition("/")[2] for f in table.inputFiles()] == ["events.parquet"]:
        # a single file: a stream needs its folder
        stream = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    else:
        stream = reader.parquet(path)
    return stream.withColumn("ets", F.col("ts").cast("timestamp")).drop("ts").withWatermark("ets", lateness)


def drained(df: DataFrame, mode: str) -> DataFrame:
    """What a stream gives once all input at hand is through. Each batch is written to the shared folder under its number, so one that is repeated replaces itself; of the complete mode the last one counts."""
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    spark.createDataFrame([], df.schema).write.parquet(f"{folder}/rows/batch=-1")

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{folder}/rows/batch={batch}")

    query = df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.parquet(f"{folder}/rows")
    if mode == "complete":
        rows = rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0])
    return rows.drop("batch")


def tumbling(spark, sf_dir):
    counts = events(spark, sf_dir).groupBy(F.window("ets", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.max("value").alias("top"))
    return drained(counts, "complete").select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "n", "top")


def sliding(spark, sf_dir):
    counts = events(spark, sf_dir).groupBy(F.window("ets", "7 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counts, "complete").select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n")


def session(spark, sf_dir):
    s = events(spark, sf_dir).groupBy("user_id", F.session_window("ets", "2 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(s, "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def _advance(old: np.ndarray, coefficients: np.ndarray, value: float) -> np.ndarray:
    """Coefficients of a window that drops its first value and takes a new last one."""
    f = np.array(KEPT)
    return (coefficients + (value - old[0]) / np.sqrt(WINDOW)) * np.exp(2j * np.pi * f / WINDOW)


def _direct(window: np.ndarray) -> np.ndarray:
    return np.fft.fft(window, norm="ortho")[list(KEPT)]


def follow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """The state of a user: how many values came, the last WINDOW of them, and their coefficients."""
    if state.exists:
        seen, window, re, im = state.get
        window, x = np.array(window), np.array(re) + 1j * np.array(im)
    else:
        seen, window, x = 0, np.zeros(0), np.zeros(len(KEPT), complex)
    rows = pd.concat(list(batches)).sort_values(["ets", "event_id"])
    for value in rows["value"]:
        seen += 1
        if len(window) < WINDOW:
            window = np.append(window, value)
            if len(window) == WINDOW:
                x = _direct(window)
            continue
        x = _advance(window, x, value)
        window = np.append(window[1:], value)
        if seen % REFRESH == 0:
            x = _direct(window)
    state.update((seen, window.tolist(), x.real.tolist(), x.imag.tolist()))
    full = len(window) == WINDOW
    yield pd.DataFrame({"user_id": [key[0]], "seen": [seen], "last": [window.tolist()], **{f"{p}{f}": [float(v) if full else None] for i, f in enumerate(KEPT) for p, v in (("re", x[i].real), ("im", x[i].imag))}})


def followed(spark, sf_dir) -> DataFrame:
    """The last state of each user: values seen, the last WINDOW of them and their coefficients, updated at each arrival."""
    columns = ", ".join(f"{p}{f} double" for f in KEPT for p in ("re", "im"))
    stream = events(spark, sf_dir).select("user_id", "ets", "event_id", "value")
    out = stream.groupBy("user_id").applyInPandasWithState(follow, f"user_id bigint, seen bigint, last array<double>, {columns}", "seen bigint, window array<double>, re array<double>, im array<double>", "update", GroupStateTimeout.NoTimeout)
    return drained(out, "update").groupBy("user_id").agg(F.max_by(F.struct("*"), "seen").alias("x")).select("x.*")


def sliding_dft(spark, sf_dir):
    """Coefficients of each user's last values."""
    return followed(spark, sf_dir).select("user_id", "seen", *((F.round(f"{p}{f}", 4) + F.lit(0.0)).alias(f"{p}{f}") for f in KEPT for p in ("re", "im")))


def series_match(spark, sf_dir, eps: float = 200.0):
    """Users whose last values are within eps of a stored pattern, a wave around 50: the kept coefficients decide first, the values themselves at last."""
    waves = {k: 50 + 20 * np.cos(2 * np.pi * k * np.arange(WINDOW) / WINDOW) for k in KEPT}
    rows = [(k, v.tolist(), *(float(x) for c in _direct(v) for x in (c.real, c.imag))) for k, v in waves.items()]
    patterns = spark.createDataFrame(rows, "pattern int, shape array<double>, " + ", ".join(f"q_{p}{f} double" for f in KEPT for p in ("re", "im")))
    gaps = [F.pow(F.col(f"{p}{f}") - F.col(f"q_{p}{f}"), F.lit(2.0)) for f in KEPT for p in ("re", "im")]
    near = F.sqrt(2 * sum(gaps[1:], gaps[0])) <= eps * (1 + 1e-9)
    users = followed(spark, sf_dir).where(F.size("last") == WINDOW)
    found = users.join(F.broadcast(patterns), near).withColumn("dist", euclid(F.col("last"), F.col("shape"))).where(F.col("dist") <= eps)
    return found.select("user_id", "pattern", (F.round("dist", 4) + F.lit(0.0)).alias("dist"))


def match(spark, sf_dir):
    """Daily windows joined with a static set of patterns: days whose mean value is near a pattern's level."""
    patterns = spark.createDataFrame([(i, 46.0 + i) for i in range(9)], "pattern int, level double")
    daily = events(spark, sf_dir).groupBy(F.window("ets", "1 day").alias("w")).agg(F.avg("value").alias("mean"))
    found = drained(daily, "complete").join(F.broadcast(patterns), F.abs(F.col("mean") - F.col("level")) <= 0.75)
    return found.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "pattern", (F.round(F.col("mean") - F.col("level"), 4) + F.lit(0.0)).alias("gap"))


def late(spark, sf_dir):
    """Append mode: windows that the watermark has passed; duplicates within it are dropped."""
    once = events(spark, sf_dir, "1 day").dropDuplicatesWithinWatermark(["event_id"])
    counts = once.groupBy(F.window("ets", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counts, "append").select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": session, "stream_sliding_dft": sliding_dft, "stream_series_match": series_match, "stream_match": match, "stream_late": late}


def oracle_sql() -> dict[str, str]:
    last = "WITH e AS (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS b, count(*) OVER (PARTITION BY user_id) AS seen FROM events), w AS (SELECT user_id, any_value(seen) AS seen, list(value ORDER BY b DESC) AS v FROM e WHERE b <= 32 GROUP BY 1)"
    dft = lambda f, k: f"round({'-' if k == 'sin' else ''}list_sum(list_transform(range(0, 32), lambda t: v[t + 1] * {k}(2 * pi() * {f} * t / 32))) / sqrt(32), 4) + 0.0::DOUBLE"
    return {
        "stream_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n, max(value) AS top FROM events GROUP BY 1, 2",
        "stream_sliding": "SELECT strftime(date_trunc('day', ts) - to_days(CAST(d AS INT)), '%Y-%m-%d') AS day, count(*) AS n FROM events, (SELECT unnest(range(0, 7)) AS d) GROUP BY 1",
        "stream_session": "WITH s AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 2 HOURS THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT user_id, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM s), c AS (SELECT user_id, k, count(*) AS n FROM n GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1",
        "stream_sliding_dft": f"{last} SELECT user_id, CAST(seen AS BIGINT) AS seen, " + ", ".join(f"{dft(f, k)} AS {p}{f}" for f in KEPT for p, k in (("re", "cos"), ("im", "sin"))) + " FROM w",
        "stream_series_match": f"{last}, p AS (SELECT CAST(k AS INT) AS pattern, list_transform(range(0, 32), lambda t: 50 + 20 * cos(2 * pi() * k * t / 32)) AS shape FROM (SELECT unnest([1, 2]) AS k)), d AS (SELECT user_id, pattern, list_distance(v, shape) AS dist FROM w, p WHERE len(v) = 32) SELECT user_id, pattern, round(dist, 4) + 0.0::DOUBLE AS dist FROM d WHERE dist <= 200.0",
        "stream_late": "WITH d AS (SELECT date_trunc('day', ts) AS day, count(DISTINCT event_id) AS n FROM events GROUP BY 1), m AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM events) SELECT strftime(day, '%Y-%m-%d') AS day, n FROM d, m WHERE day + INTERVAL 1 DAY <= mark",
        "stream_match": "WITH d AS (SELECT date_trunc('day', ts) AS day, avg(value) AS mean FROM events GROUP BY 1) SELECT strftime(day, '%Y-%m-%d') AS day, CAST(p AS INT) AS pattern, round(mean - (46.0::DOUBLE + p), 4) + 0.0::DOUBLE AS gap FROM d, (SELECT unnest(range(0, 9)) AS p) WHERE abs(mean - (46.0::DOUBLE + p)) <= 0.75",
    }
