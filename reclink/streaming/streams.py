"""Streams over the events table and their drained results."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reclink.sources.store import folder


def events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events as a file stream, with ts as an instant."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run the stream over all that is there; the result as a batch frame from files.

    append keeps every batch's rows, complete the last batch's, update the rows of all
    batches.  Batches go to folders by number, so a repeated batch replaces itself.
    """
    spark = stream.sparkSession
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"
    seen: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        if each:
            each(batch, number)
        batch.write.mode("overwrite").parquet(f"{base}/out/{number}")
        seen.append(number)

    run = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    run.awaitTermination()
    numbers = sorted(set(seen))
    if mode == "complete":
        numbers = numbers[-1:]
    if not numbers:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{base}/out/{n}" for n in numbers])


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "1 day").groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("v"))


def sliding(stream: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "1 day").groupBy(F.window("ts", width, slide)).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.withWatermark("ts", "1 day").groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def running_counts(stream: DataFrame, key: str) -> DataFrame:
    """key, n: how often each key was seen, kept as state and emitted as it grows."""

    def count(keys, frames: Iterator[pd.DataFrame], state):
        n = state.get[0] if state.exists else 0
        n += sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({key: [keys[0]], "n": [n]})

    return stream.select(key).groupBy(key).applyInPandasWithState(count, f"{key} {dict(stream.dtypes)[key]}, n long", "n long", "update", "NoTimeout")


ARRIVED = "combo_id int, sig_hash long, a_id string, b_id string, dead boolean"


def incremental_pairs(signatures: DataFrame, cap: int) -> DataFrame:
    """Links arriving records: of signatures (record_id, side 'a' or 'b', combo_id, sig_hash)
    the pairs that each newcomer makes with those that were there before.

    A signature's state is the records that have it, at most `cap` a side.  One that more
    records share is dead from then on: a row says so, its state is emptied, and it makes no
    more pairs, so state and work stay bounded per signature.  State lives in the stream's
    checkpoint and survives a restart.
    """

    def meet(key, frames: Iterator[pd.DataFrame], state):
        held, dead = ({"a": [], "b": []}, False)
        if state.exists:
            left, right, dead = state.get
            held = {"a": list(left), "b": list(right)}
        out = []
        if not dead:
            fresh = pd.concat(list(frames)).drop_duplicates(["record_id", "side"]).sort_values(["side", "record_id"])
            for record, side in zip(fresh["record_id"], fresh["side"]):
                if record in held[side]:
                    continue
                other = held["b" if side == "a" else "a"]
                out += [(record, x) if side == "a" else (x, record) for x in other]
                held[side].append(record)
                if len(held[side]) > cap:
                    out, held, dead = [(None, None)], {"a": [], "b": []}, True
                    break
            state.update((held["a"], held["b"], dead))
        n = len(out)
        yield pd.DataFrame({"combo_id": [int(key[0])] * n, "sig_hash": [int(key[1])] * n, "a_id": [x for x, _ in out], "b_id": [x for _, x in out], "dead": [dead] * n})

    rows = signatures.select("combo_id", "sig_hash", F.col("record_id").cast("string").alias("record_id"), "side")
    return rows.groupBy("combo_id", "sig_hash").applyInPandasWithState(meet, ARRIVED, "a array<string>, b array<string>, dead boolean", "update", "NoTimeout")


def live_pairs(arrived: DataFrame) -> DataFrame:
    """a_id, b_id, common of drained incremental_pairs: over signatures that did not die."""
    dead = arrived.where("dead").select("combo_id", "sig_hash").distinct()
    return arrived.where("NOT dead").join(dead, ["combo_id", "sig_hash"], "left_anti").groupBy("a_id", "b_id").agg(F.count(F.lit(1)).alias("common"))
