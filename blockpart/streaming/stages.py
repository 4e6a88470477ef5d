"""Partitions of growing graphs: stage by stage, cold or warm; and stream operators on edges."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor

from blockpart.functions.math import string_id
from blockpart.operators import metrics, node, stages
from blockpart.operators.relops import settled
from blockpart.plans.search import FitConfig, endpoints, fit


def warm_start(edges: DataFrame, assign: DataFrame, new: str = "majority") -> DataFrame:
    """A start for the graph so far: old nodes keep their blocks; new ones stand alone or go where most of their weight is (ties to the least block)."""
    nodes = endpoints(edges)
    if new == "majority":
        known = node.node_block(edges.where("src <> dst"), assign).withColumn("k", F.col("k_out") + F.col("k_in"))
        best = known.groupBy("i").agg(F.max_by("t", F.struct("k", -F.col("t"))).alias("t"))
        start = nodes.join(assign, "i", "left").join(best, "i", "left")
        return start.select("i", F.coalesce("b", "t", -1 - F.col("i")).alias("b"))
    return nodes.join(assign, "i", "left").select("i", F.coalesce("b", -1 - F.col("i")).alias("b"))


def run(staged: DataFrame, truth: DataFrame | None = None, warm: str = "carry", new: str = "singleton", cfg: FitConfig | None = None, bracket: str = "full") -> list[dict]:
    """Finish each stage before the next is read; a row of measures per stage.

    warm 'carry': the last partition is the start, new nodes alone ('singleton') or where most of their weight is ('majority'). bracket 'reuse': the first tries
    are twice, once and half the last number of blocks, in place of halving from the start's.
    """
    rows, assign, cfg = [], None, cfg or FitConfig()
    for k in sorted(r[0] for r in staged.select("stage").distinct().collect()):
        edges = settled(stages.upto(staged, k).groupBy("src", "dst").agg(F.sum("w").alias("w")))
        begin = time.monotonic()
        start = warm_start(edges, assign, new) if warm == "carry" and assign is not None else None
        last = rows[-1]["blocks"] if rows else None
        assign, history = fit(edges, None, replace(cfg, around=last if bracket == "reuse" else None), start)
        assign = settled(assign)
        seconds = time.monotonic() - begin
        size = edges.agg(F.sum("w")).first()[0]
        row = {"stage": k, "n": assign.count(), "e": size, "blocks": assign.select("b").distinct().count(), "h_val": min(x["h_val"] for x in history), "tries": len(history) - 1, "sec": seconds, "rate": size / seconds, "warm": start is not None}
        if truth is not None:
            row |= metrics.report(truth, assign).first().asDict()
        rows.append(row)
    return rows


def windowed(events: DataFrame, kind: str = "tumbling", watermark: str = "1 day") -> DataFrame:
    """Edge weight per window of events(ts, src, dst, w); ts must be a TIMESTAMP."""
    over = {"tumbling": lambda: F.window("ts", "1 day"), "sliding": lambda: F.window("ts", "2 days", "1 day"), "session": lambda: F.session_window("ts", "10 minutes")}[kind]()
    rows = events.withWatermark("ts", watermark) if events.isStreaming else events
    keys = [over.alias("win")] + (["src"] if kind == "session" else [])
    return rows.groupBy(*keys).agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n")).select(F.col("win.start").alias("start"), F.col("win.end").alias("end"), *(["src"] if kind == "session" else []), "w", "n")


class RunningDegree(StatefulProcessor):
    """Per node: weight so far, and the first stage in which it was seen."""

    def init(self, handle) -> None:
        self.state = handle.getValueState("degree", "weight double, stage int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        weight, stage = self.state.get() if self.state.exists() else (0.0, None)
        for pdf in rows:
            weight += float(pdf["w"].sum())
            low = int(pdf["stage"].min())
            stage = low if stage is None else min(stage, low)
        self.state.update((weight, stage))
        yield pd.DataFrame({"i": [key[0]], "weight": [weight], "stage": pd.array([stage], dtype="int32")})

    def close(self) -> None:
        pass


def running_degrees(incident: DataFrame) -> DataFrame:
    """incident(i, w, stage) as a stream to i, weight, stage after each batch (needs the RocksDB state store)."""
    return incident.groupBy("i").transformWithStateInPandas(statefulProcessor=RunningDegree(), outputStructType="i bigint, weight double, stage int", outputMode="Update", timeMode="None")


def event_edges(events: DataFrame) -> DataFrame:
    """events as edges from user to kind of event: ts (cast from NTZ), src 4 user, dst the kind's own id, w."""
    return events.select(F.col("ts").cast("timestamp").alias("ts"), (F.col("user_id") * 4).alias("src"), string_id(F.col("event_type"), 1).alias("dst"), F.col("value").alias("w"), "event_id")


def deduplicated(events: DataFrame, key: str = "event_id", watermark: str = "1 day") -> DataFrame:
    """Each event once, however often it arrives within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key])


#: State on disk beside each executor, with bounded memory: one row a key need not fit the heap.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "300",
}


def finished(out: DataFrame, mode: str, path: str) -> DataFrame:
    """What a stream gives once its source is read to the end, as a table under `path`: no row passes the driver. 'complete' keeps the last batch, 'append' all."""
    spark = out.sparkSession
    was = {k: spark.conf.get(k, None) for k in STATE}
    done: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        done.append(number)

    try:
        for k, v in STATE.items():
            spark.conf.set(k, v)
        run = out.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-check").trigger(availableNow=True)
        run.foreachBatch(keep).start().awaitTermination()
    finally:
        for k, v in was.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    kept = [f"{path}/batch={k}" for k in (done if mode == "append" else done[-1:])]
    return spark.read.schema(out.schema).parquet(*kept) if kept else spark.createDataFrame([], out.schema)


def partition_stream(source: DataFrame, checkpoint: str, cfg: FitConfig | None = None) -> list[dict]:
    """foreachBatch over a stream of edges: each batch adds its edges and is partitioned from the last blocks. One row per batch.

    Batches, partitions and measures are tables beside the checkpoint, each under its batch number; a restarted stream goes on from them, and a batch that is
    run again overwrites its own.
    """
    spark: SparkSession = source.sparkSession
    held = f"{checkpoint.rstrip('/')}-held"
    part = lambda kind, k: f"{held}/{kind}/batch={k}"
    schema = "src bigint, dst bigint, w double"

    def step(batch: DataFrame, number: int) -> None:
        batch.groupBy("src", "dst").agg(F.sum("w").cast("double").alias("w")).write.mode("overwrite").parquet(part("edges", number))
        edges = spark.read.schema(schema + ", batch bigint").parquet(f"{held}/edges").where(F.col("batch") <= number)
        edges = edges.groupBy("src", "dst").agg(F.sum("w").alias("w"))
        start = warm_start(edges, spark.read.schema("i bigint, b bigint").parquet(part("assign", number - 1)), "singleton") if number else None
        assign, history = fit(edges, None, cfg, start)
        assign.write.mode("overwrite").parquet(part("assign", number))
        row = (number, edges.agg(F.sum("w")).first()[0], assign.select("b").distinct().count(), min(x["h_val"] for x in history))
        spark.createDataFrame([row], "number bigint, e double, blocks bigint, h_val double").coalesce(1).write.mode("overwrite").parquet(part("rows", number))

    source.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.schema("number bigint, e double, blocks bigint, h_val double").parquet(f"{held}/rows").orderBy("number").collect()
    return [{"batch": r["number"], "e": r["e"], "blocks": r["blocks"], "h_val": r["h_val"]} for r in rows]
