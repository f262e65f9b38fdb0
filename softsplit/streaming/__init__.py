"""Structured Streaming around a frozen model: scoring, windows, drift, state, joins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, functions as F

from ..operators.model import SSBModel
from ..store import Workspace


def score_stream(events: DataFrame, model: SSBModel) -> DataFrame:
    """Stateless scoring; mu and sd are those of training."""
    return model.transform(events)


def tumbling_counts(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    seen = events.withWatermark("ts", late)
    return seen.groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding_mean(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.avg("value").alias("mean"), F.count(F.lit(1)).alias("n"))


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def without_copies(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drift_statistics(events: DataFrame, z: str, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Sums of raw outputs by window and cell; the training statistics are sums too, so they compare."""
    long = events.withWatermark("ts", late).select("ts", F.posexplode(z).alias("cell", "z"))
    return long.groupBy(F.window("ts", width), "cell").agg(F.count(F.lit(1)).alias("n"), F.sum("z").alias("s"), F.sum(F.col("z") * F.col("z")).alias("ss"))


def with_profile(events: DataFrame, profile: DataFrame, key: str = "user_id") -> DataFrame:
    """Stream-static join."""
    return events.join(profile, key, "left")


def click_to_purchase(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream join of a user's click and purchases after it."""
    c = clicks.withWatermark("ts", late).select(F.col("user_id").alias("c_user"), F.col("ts").alias("c_ts"), F.col("event_id").alias("click_id"))
    p = purchases.withWatermark("ts", late).select(F.col("user_id").alias("p_user"), F.col("ts").alias("p_ts"), F.col("event_id").alias("purchase_id"))
    near = (F.col("c_user") == F.col("p_user")) & (F.col("p_ts") >= F.col("c_ts")) & (F.col("p_ts") <= F.col("c_ts") + F.expr(f"interval {within}"))
    return c.join(p, near)


def running_by_user(events: DataFrame, last: int = 3) -> DataFrame:
    """(user_id, n, total, last_values) after each batch; state holds n, total and the last values of a user."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total, values = state.get if state.exists else (0, 0.0, [])
        values = list(values)
        for pdf in batches:
            pdf = pdf.sort_values("ts")
            n, total = n + len(pdf), total + float(pdf["value"].sum())
            values = [*values, *pdf["value"].tolist()][-last:]
        state.update((n, total, values))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total], "last_values": [values]})

    out = "user_id long, n long, total double, last_values array<double>"
    kept = "n long, total double, last_values array<double>"
    return events.select("user_id", "ts", "value").groupBy("user_id").applyInPandasWithState(step, out, kept, "update", "NoTimeout")


def run_available(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and gives the rows it emitted.

    Rows (Parquet) and state lie in the folder that driver and executors share, so the driver holds neither.
    The file sink takes appended rows only: other modes write a folder for each batch, and complete mode gives the last.
    """
    spark = stream.sparkSession
    kept = Workspace(spark, name)
    writer = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", f"{kept.root}/state").trigger(availableNow=True)
    written: dict[int, str] = {}
    if mode == "append":
        writer = writer.format("parquet").option("path", f"{kept.root}/rows")
    else:

        def each(batch: DataFrame, number: int) -> None:
            written[number] = f"{kept.root}/rows/{number}"
            batch.write.mode("overwrite").parquet(written[number])

        writer = writer.foreachBatch(each)
    writer.start().awaitTermination()
    if mode == "append":
        return spark.read.schema(stream.schema).parquet(f"{kept.root}/rows")
    paths = [written[max(written)]] if written and mode == "complete" else list(written.values())
    return spark.read.schema(stream.schema).parquet(*paths) if paths else spark.createDataFrame([], stream.schema)


def run_without_copies(stream: DataFrame, name: str, late: str = "1 hour") -> DataFrame:
    """without_copies and run_available in one: the rows that went out are the keys seen, so no state store holds a key.

    A store keeps every key of a batch in the memory of executors; here a batch is aggregated, which may spill, and joined
    to the rows of earlier batches. As in a store, the watermark that drops late rows and old keys is that of the batch
    before; it follows the rows that went out.
    """
    spark = stream.sparkSession
    kept = Workspace(spark, name)
    written: dict[int, str] = {}
    read = lambda paths: spark.read.schema(stream.schema).parquet(*paths)

    def each(batch: DataFrame, number: int) -> None:
        earlier = [written[n] for n in sorted(written) if n < number]
        seen = read(earlier) if earlier else None
        newest = read(earlier[:-1]).agg(F.unix_micros(F.max("ts"))).first()[0] if earlier[1:] else None
        if newest is not None:
            span = F.expr(f"interval {late}")
            mark = F.timestamp_micros(F.lit(newest)) - span
            batch = batch.filter(F.coalesce(F.col("ts") > mark, F.lit(True)))
            seen = seen.filter(F.coalesce(F.col("ts") + span > mark, F.lit(True)))
        if seen is not None:
            held = seen.select(F.col("event_id").alias("seen_id"))
            batch = batch.join(held, F.col("event_id").eqNullSafe(F.col("seen_id")), "left_anti")
        path = f"{kept.root}/rows/{number}"
        batch.dropDuplicates(["event_id"]).write.mode("overwrite").parquet(path)
        written[number] = path

    stream.writeStream.queryName(name).option("checkpointLocation", f"{kept.root}/state").trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return read(written.values()) if written else spark.createDataFrame([], stream.schema)


def boost_by_batch(stream: DataFrame, fit_round, model: SSBModel):
    """Adds one round a micro-batch through fit_round(batch, model) -> Round; earlier rounds stay frozen."""

    def each(batch: DataFrame, _: int) -> None:
        if not batch.isEmpty():
            model.rounds.append(fit_round(batch, model))

    return stream.writeStream.foreachBatch(each).trigger(availableNow=True).start()
