"""Structured Streaming around the joins. Every query runs on the events table's schema or one given; checkpoints go where the session's shared folder is."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridjoin.operators.baselines import cascade_join
from gridjoin.plans.covermix import cover_mix_join
from gridjoin.plans.query import Atom, JoinQuery
from gridjoin.sources.tables import shared_dir


def checkpoint_of(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"


def stream_degrees(sdf: DataFrame, keys: list[str], window: str, watermark: str, ts: str = "ts", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Degrees of keys in tumbling, sliding or session windows; rows later than the watermark are dropped."""
    when = F.session_window(ts, gap) if gap else F.window(ts, window, slide)
    grouped = sdf.withWatermark(ts, watermark).groupBy(when.alias("w"), *keys).agg(F.count("*").alias("deg"))
    return grouped.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), *keys, "deg")


def stream_dedup(sdf: DataFrame, keys: list[str], watermark: str, ts: str = "ts") -> DataFrame:
    return sdf.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(keys)


def stream_interval_join(a: DataFrame, b: DataFrame, key: str, seconds: int, watermark: str, ts: str = "ts") -> DataFrame:
    """Pairs of one key with b at most so many seconds after a; both sides' state is bounded by the watermarks."""
    left = a.withWatermark(ts, watermark).select(*[F.col(c).alias(f"a_{c}") for c in a.columns])
    right = b.withWatermark(ts, watermark).select(*[F.col(c).alias(f"b_{c}") for c in b.columns])
    cond = F.expr(f"a_{key} = b_{key} AND b_{ts} >= a_{ts} AND b_{ts} <= a_{ts} + INTERVAL {seconds} SECONDS")
    return left.join(right, cond)


def heavy_keys_stateful(sdf: DataFrame, key: str, up: int, down: float, half_life: int = 3) -> DataFrame:
    """Keys that become heavy (decayed count of at least ``up``) or light again (below ``down``): one row at each change, with hysteresis.
    The count halves over ``half_life`` batches without the key."""
    kind = sdf.schema[key].dataType.simpleString()

    def update(k, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        count, heavy = state.get if state.exists else (0.0, False)
        new = sum(len(f) for f in frames)
        count = count * 0.5 ** (1 / half_life) + new
        now = count >= up if not heavy else count >= down
        state.update((float(count), bool(now)))
        if now != heavy:
            yield pd.DataFrame({key: [k[0]], "heavy": [now], "cnt": [float(count)]})

    return sdf.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, heavy boolean, cnt double", "cnt double, heavy boolean", "append", "NoTimeout")


def run_to_end(sdf: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there (availableNow) into files, and reads them; a complete or update mode goes through memory."""
    spark = sdf.sparkSession
    if mode == "append":
        path = checkpoint_of(spark, f"{name}-out")
        q = sdf.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint_of(spark, name)).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(sdf.schema).parquet(path)
    table = f"{name}_{uuid.uuid4().hex}"
    q = sdf.writeStream.outputMode(mode).format("memory").queryName(table).option("checkpointLocation", checkpoint_of(spark, name)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(table)


def delta_join(old: JoinQuery, deltas: dict[str, DataFrame], p: int | None = None) -> DataFrame:
    """Results that new tuples add: one term for each changed atom, with the new state of the atoms before it and the old state of those after.
    deltas must not repeat old tuples; the terms are then disjoint."""
    out = None
    for i, a in enumerate(old.atoms):
        if a.name not in deltas:
            continue
        atoms = []
        for j, b in enumerate(old.atoms):
            grown = b.df.unionByName(deltas[b.name]) if b.name in deltas else b.df
            atoms.append(Atom(b.name, deltas[b.name] if i == j else grown if j < i else b.df))
        term = cover_mix_join(JoinQuery(atoms), p) if p else cascade_join(JoinQuery(atoms))
        out = term if out is None else out.unionByName(term)
    return out


def stream_multiway_join(sdf: DataFrame, name: str, fixed: dict[str, DataFrame], p: int, path: str) -> DataFrame:
    """Joins each micro-batch of one atom's tuples with fixed relations. Results are a set, as of the whole stream: tuples of earlier batches are kept in a
    table, and only new ones are joined. Each batch's tuples and results are folders of their own, so a batch run again replaces them."""
    spark = sdf.sparkSession
    seen, schema = f"{path}-seen", sdf.schema

    def batch(df: DataFrame, number: int) -> None:
        new = df.distinct()
        if number:
            past = spark.read.schema(schema).option("basePath", seen).parquet(f"{seen}/batch=*").where(F.col("batch") < number)
            same = [F.col(f"n.`{c}`").eqNullSafe(F.col(f"p.`{c}`")) for c in df.columns]
            new = new.alias("n").join(past.alias("p"), same, "left_anti")
        new.write.mode("overwrite").parquet(f"{seen}/batch={number}")
        fresh = spark.read.schema(schema).parquet(f"{seen}/batch={number}")
        cover_mix_join(JoinQuery({name: fresh} | fixed), p).write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = sdf.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint_of(spark, "multiway")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path).drop("batch")
