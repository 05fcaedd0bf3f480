"""Streams of detections: against a static catalog, in windows and sessions, against another stream, without repeats."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.evidence import ln_bayes_flat
from ..functions.plan import sealed, shared_folder
from ..functions.sphere import PER_RADIAN, angle_of
from ..operators.match import BROADCAST_ROWS
from ..operators.zones import MOST_LEVELS, Level, choose_grid, pair_table, sky_columns


def read_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A file stream of Parquet with the schema of what is there now."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rstrip("/").rpartition("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", name).parquet(folder)


def error_levels(static_as: float, chord: float, limit: float) -> list[Level]:
    """Levels by the inverse of a row's error in arc seconds, each with the widest chord of its rows against errors of static_as at most."""

    def reach(low: float, high: float) -> float:
        # 2 v (ln(2 / limit) - ln v) has its maximum at ln v = ln(2 / limit) - 1.
        least, most = ((s / PER_RADIAN) ** 2 for s in (low, math.hypot(high, static_as)))
        v = max(least, min(most, 2 / limit / math.e))
        return min(chord, math.sqrt(max(0.0, 2 * v * (math.log(2 / limit) - math.log(v)))) * (1 + 1e-9) + 1e-12)

    out, low, high = [], 0.0, 1.0
    while len(out) < MOST_LEVELS - 1 and (wide := reach(low, high)) < chord:
        out.append(Level(1 / high, wide, choose_grid(angle_of(wide))))
        low, high = high, 2 * high
    return [*out, Level(0.0, chord, choose_grid(angle_of(chord)))]


def stream_match(stream: DataFrame, static: DataFrame, chord: float, limit: float) -> DataFrame:
    """Stream rows (event_id, ra, dec, sigma_as) with static ones (key, ra, dec, static_s) that reach the limit: the batch zone join.

    Each row searches as far as its own error can reach within the chord: levels of errors that double, whatever the stream brings.
    Only a static side known to be small, its rows of all levels counted, is broadcast; a micro-batch never is.
    """
    worst, n = static.agg(F.max("static_s"), F.count(F.lit(1))).first()
    levels = error_levels(float(worst or 0.0), chord, limit)
    large = n * len(levels) > BROADCAST_ROWS
    a = sky_columns(stream, ("ra", "dec")).drop("ra", "dec")
    b = sky_columns(static, ("ra", "dec")).drop("ra", "dec")
    s = F.col("sigma_as")
    a = a.withColumn("__sw", F.when(s == 0, float("inf")).when(F.isnan(s), 0.0).otherwise(1 / s))
    pairs = pair_table(a, b if large else F.broadcast(b), chord, levels=levels, level_weight=F.col("__sw"), shuffled=large)
    w = [PER_RADIAN * PER_RADIAN / (F.col(s) * F.col(s)) for s in ("sigma_as", "static_s")]
    out = sealed(pairs, {"ln_bf": ln_bayes_flat("__c2", *w)}).filter(F.col("ln_bf") >= math.log(limit))
    return out.select(*[c for c in out.columns if not c.startswith("__")])


def windowed(stream: DataFrame, time: str, key: str, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Rows by window and key; late rows past the watermark are left out."""
    return stream.withWatermark(time, late).groupBy(F.window(time, length, slide) if slide else F.window(time, length), key).agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sessions(stream: DataFrame, time: str, key: str, gap: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap), key).agg(F.count("*").alias("n"))


def without_repeats(stream: DataFrame, key: str, time: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def stream_pairs(a: DataFrame, b: DataFrame, key: str, seconds: int, late: str = "1 hour") -> DataFrame:
    """Rows of two streams with an equal key (a cell, say) within some seconds of one another; both have a column ts."""
    x = a.withWatermark("ts", late).select(*[F.col(c).alias(f"a_{c}") for c in a.columns])
    y = b.withWatermark("ts", late).select(*[F.col(c).alias(f"b_{c}") for c in b.columns])
    near = F.expr(f"b_ts BETWEEN a_ts - INTERVAL {seconds} SECONDS AND a_ts + INTERVAL {seconds} SECONDS")
    return x.join(y, (F.col(f"a_{key}") == F.col(f"b_{key}")) & near)


def running_positions(stream: DataFrame, key: str) -> DataFrame:
    """The best position of each key so far: sums of weighted vectors, so arrival order only matters for rounding."""
    s = sky_columns(stream, ("ra", "dec"))
    w = PER_RADIAN * PER_RADIAN / (F.col("sigma_as") * F.col("sigma_as"))
    return s.groupBy(key).agg(*[F.sum(w * F.col(f"__{c}")).alias(f"a{c}") for c in "xyz"], F.sum(w).alias("weight"), F.count("*").alias("n"))


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All that is there now, through the streaming engine into Parquet files of the shared folder, one folder for each micro-batch.

    append and update give all batches' rows; complete gives the last batch, which holds all.
    """
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/streams/{name}-{uuid.uuid4().hex[:8]}"
    written: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/batch={number}")
        written.append(number)

    q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{root}/_checkpoint").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if not written:
        return spark.createDataFrame([], stream.schema)
    paths = [f"{root}/batch={n}" for n in (sorted(set(written)) if mode != "complete" else [max(written)])]
    return spark.read.schema(stream.schema).parquet(*paths).select(*stream.columns)
