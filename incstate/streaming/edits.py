"""Streams of edits: windows of iterations, late edits, repeated edits, and circuits kept as state."""

from __future__ import annotations

import json
import os
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from incstate.plans.store import shared_folder
from incstate.plans.small import SmallCircuit
from incstate.plans.wide import Gate


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int | None = None) -> DataFrame:
    """The ``events`` table as a stream; its local times are taken as UTC whatever the session's zone."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    utc = F.expr("timestamp_micros(timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01', ts))")
    return reader.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", utc)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream until its input ends and read what it wrote."""
    spark = stream.sparkSession
    base = os.path.join(shared_folder(spark), f"stream-{uuid.uuid4().hex}")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{base}/out")


def iterations(edits: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Edits counted by user and window: a window is an iteration."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return edits.withWatermark("ts", late).groupBy(span, "user_id").agg(F.count("*").alias("edits"), F.sum((F.col("event_type") == "error").cast("long")).alias("removals"))


def bursts(edits: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Edits of a user without a longer pause are one iteration."""
    return edits.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("edits"))


def once(edits: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each edit once, by its id, within the watermark."""
    return edits.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def confirmed(edits: DataFrame, wait: str = "2 hours") -> DataFrame:
    """Signups with a purchase of the same user within ``wait``: an interval join of two streams."""
    left = edits.where("event_type = 'signup'").select(F.col("user_id").alias("user"), F.col("ts").alias("opened"), "event_id").withWatermark("opened", "1 hour")
    right = edits.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought"), F.col("event_id").alias("purchase_id")).withWatermark("bought", "1 hour")
    within = F.expr(f"user = user_id AND bought >= opened AND bought <= opened + interval {wait}")
    return left.join(right, within).select("event_id", "purchase_id")


def named(edits: DataFrame, kinds: DataFrame) -> DataFrame:
    """Edits with a static table of kinds."""
    return edits.join(F.broadcast(kinds), "event_type")


STATE_OUT = "circuit_id bigint, live_gates bigint, edits bigint, p0 double"


def _keep_circuit(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Fold one user's edits into the live gates of a circuit of 4 qubits, and report it."""
    live, count = json.loads(state.get[0]) if state.exists else ([], 0)
    for frame in frames:
        for e in frame.sort_values(["ts", "event_id"]).itertuples():
            count += 1
            k = json.loads(e.props)["k"]
            t = k % 4
            kind = {"click": "CNOT", "view": "H", "purchase": "RZ"}.get(e.event_type)
            if kind:
                live.append([kind, t, (t + 1 + k // 4 % 3) % 4, 3.141592653589793 * 2 * k / 100])
            elif e.event_type == "error" and live:
                live.pop()
    state.update((json.dumps([live, count]),))
    circuit = SmallCircuit(4, 2)
    for number, (kind, t, c, theta) in enumerate(live):
        circuit.insert(number, number, Gate(kind, (t, c) if kind == "CNOT" else (t,), theta))
    circuit.update()
    yield pd.DataFrame({"circuit_id": [key[0]], "live_gates": [len(live)], "edits": [count], "p0": [abs(circuit.final[0]) ** 2]})


def stateful_circuits(edits: DataFrame) -> DataFrame:
    """Users' circuits as streaming state: the edit list is the state, and each trigger reports the circuit."""
    return edits.groupBy("user_id").applyInPandasWithState(_keep_circuit, STATE_OUT, "log string", "update", GroupStateTimeout.NoTimeout)


def update_sink(stream: DataFrame, update: Callable[[DataFrame, int], None], log: str) -> None:
    """Run ``update`` on each micro-batch until the input ends; it must be idempotent by batch number."""
    stream.writeStream.foreachBatch(update).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
