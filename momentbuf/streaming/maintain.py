"""Streams: windowed moments with watermarks, additive buffer maintenance, keyed state, late rows."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions.scalars import power
from momentbuf.operators.lagrange_buffer import build_lagrange
from momentbuf.sources.arrays import IndexedArray
from momentbuf.sources.store import append_delta, shared_path


def event_stream(spark: SparkSession, path: str, schema, ts: str = "ts") -> DataFrame:
    """A file stream with its event time in the session's zone (watermarks need one)."""
    return spark.readStream.schema(schema).parquet(path).withColumn("at", F.col(ts).cast("timestamp"))


def _states(order: int) -> list:
    i, v = F.col("i"), F.col("v")
    return [F.count("*").alias("cnt"), *[F.sum(power(i, k) * v).alias(f"m{k}") for k in range(order + 1)]]


def tumbling_moments(stream: DataFrame, width: str, order: int = 1, late: str | None = "2 days") -> DataFrame:
    """Additive states of windows: columns at, i (offset), v are expected."""
    s = stream.withWatermark("at", late) if late else stream
    return s.groupBy(F.window("at", width)).agg(*_states(order))


def sliding_moments(stream: DataFrame, width: str, slide: str, order: int = 1, late: str | None = "2 days") -> DataFrame:
    s = stream.withWatermark("at", late) if late else stream
    return s.groupBy(F.window("at", width, slide)).agg(*_states(order))


def session_moments(stream: DataFrame, gap: str, key: str, order: int = 0, late: str | None = "2 days") -> DataFrame:
    s = stream.withWatermark("at", late) if late else stream
    return s.groupBy(key, F.session_window("at", gap)).agg(*_states(order))


def deduplicated(stream: DataFrame, key: str, late: str = "2 days") -> DataFrame:
    return stream.withWatermark("at", late).dropDuplicatesWithinWatermark([key])


def drain(df: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there now and return what it leaves: files that tasks write below the shared folder, so the driver holds no rows.

    Each batch of complete mode is the whole answer, and the last one holds; other modes' batches add up.
    """
    spark, path, written = df.sparkSession, shared_path(df.sparkSession, name), {}

    def batch(out: DataFrame, batch_id: int) -> None:
        at = f"{path}/batch-{batch_id}"
        out.write.mode("overwrite").parquet(at)
        written[batch_id] = at

    df.writeStream.outputMode(mode).foreachBatch(batch).trigger(availableNow=True).start().awaitTermination()
    paths = [written[max(written)]] if written and mode == "complete" else list(written.values())
    return spark.read.schema(df.schema).parquet(*paths) if paths else spark.createDataFrame([], df.schema)


def maintain(stream: DataFrame, path: str, n: int, b: int, order: int = 4, levels: int = 1, checkpoint: str | None = None, mode: str = "exact"):
    """Log the buffer cells of every batch of updates (idx, delta); a replayed batch overwrites itself, so none counts twice."""

    def batch(df: DataFrame, batch_id: int) -> None:
        delta = IndexedArray(df.groupBy("idx").agg(F.sum("delta").alias("val")), n)
        append_delta(build_lagrange(delta, b, order, levels, mode).df, path, batch_id)

    w = stream.writeStream.foreachBatch(batch).trigger(availableNow=True)
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()


def late_report(events: DataFrame, watermark: str, batch: str) -> DataFrame:
    """batch, accepted, late: rows older than the greatest time of earlier batches less the allowed delay."""
    from pyspark.sql import Window

    top = events.groupBy(batch).agg(F.max("at").alias("top"))
    line = top.select(batch, (F.max("top").over(Window.orderBy(batch).rowsBetween(Window.unboundedPreceding, -1)) - F.expr(f"INTERVAL {watermark}")).alias("line"))
    late = F.coalesce(F.col("at") < F.col("line"), F.lit(False))
    return events.join(F.broadcast(line), batch).groupBy(batch).agg(F.sum((~late).cast("long")).alias("accepted"), F.sum(late.cast("long")).alias("late"))


def stateful_buffer(stream: DataFrame, b: int, group: int = 64, order: int = 2) -> DataFrame:
    """grp, cell, v, version: cells of a buffer of any order kept as state, one state for each group of cells; stream: idx, delta, at. Of a cell's rows the one of the greatest version holds."""
    import pandas as pd

    from momentbuf.functions.weights import Stencil

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        cells, version = {}, 0
        if state.exists:
            ids, sums, version = state.get
            cells = dict(zip(ids, sums, strict=True))
        for f in frames:
            for c, w in f.groupby("cell")["w"].sum().items():
                cells[int(c)] = cells.get(int(c), 0.0) + float(w)
        state.update((list(cells), list(cells.values()), version + 1))
        yield pd.DataFrame({"grp": [key[0]] * len(cells), "cell": list(cells), "v": list(cells.values()), "version": [version + 1] * len(cells)})

    st = Stencil.of(order)
    parts = ", ".join(f"struct(idx div {b} + {k} AS cell, {st.weight(k, f'(idx % {b})', b)} * delta AS w)" for k in st.nodes)
    rows = stream.select(F.expr(f"inline(array({parts}))")).where("w <> 0 AND cell >= 0").withColumn("grp", F.expr(f"cell div {group}"))
    return rows.groupBy("grp").applyInPandasWithState(step, "grp long, cell long, v double, version long", "cells array<long>, sums array<double>, version long", "update", "NoTimeout")
