"""Schedules of the node update: one sweep old for all, in batches, within partitions, one node after another."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.functions.math import u01
from blockpart.operators import node, stats
from blockpart.operators.relops import forget, passing, settled

#: Cells of M that the schedules with newest blocks hold in a worker at most, and nodes of the sequential one.
HELD_CELLS = 1_000_000
SEQUENTIAL_NODES = 100_000


def batched_with(edges: DataFrame, assign: DataFrame, counts: DataFrame, blocks: int, seed: int, it: int, q: int = 1, beta: float = 3.0, explore: float | None = None, damp: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """New assign and counts, both written: q hashed batches, counts refreshed from moved edges after each."""
    for k in range(q):
        draw = u01(seed, "batch", it, F.col("i"))
        only = F.floor(draw * q) == k if q > 1 else draw < damp if damp < 1 else None
        with passing(edges.sparkSession) as keep:
            after = settled(node.apply_moves(assign, node.evaluate(edges, assign, counts, blocks, seed, it, beta, explore, only)))
            now = settled(node.refresh_cells(counts, edges, assign, after))
            keep(after, now)
        if k:  # the batch before has been read for the last time
            forget(edges.sparkSession, assign._settled_at, counts._settled_at)
        assign, counts = after, now
    return assign, counts


def swept(edges: DataFrame, assign: DataFrame, counts: DataFrame, blocks: int, cfg, it: int) -> tuple[DataFrame, DataFrame]:
    """One sweep in the schedule of the configuration."""
    if cfg.schedule in ("sync", "batched"):
        return batched_with(edges, assign, counts, blocks, cfg.seed, it, cfg.batches, cfg.step_beta, cfg.explore, cfg.damp)
    if cfg.schedule == "sequential":
        after = settled(sequential(edges, assign, blocks, cfg.seed, it, cfg.step_beta, cfg.explore, counts))
    else:
        after = settled(partition_local(edges, assign, blocks, cfg.seed, it, cfg.step_beta, cfg.parts, cfg.explore, counts))
    return after, settled(node.refresh_cells(counts, edges, assign, after))


def synchronous(edges: DataFrame, assign: DataFrame, blocks: int, seed: int, it: int, beta: float = 3.0, explore: float | None = None, damp: float = 1.0, counts: DataFrame | None = None) -> DataFrame:
    """New assign; all nodes see the previous sweep. damp < 1: only so large a hashed share may move. Counts that are known need not be made again."""
    only = None if damp >= 1 else u01(seed, "batch", it, F.col("i")) < damp
    counts = settled(stats.cells(edges, assign)) if counts is None else counts
    return node.apply_moves(assign, node.evaluate(edges, assign, counts, blocks, seed, it, beta, explore, only))


def batched(edges: DataFrame, assign: DataFrame, blocks: int, seed: int, it: int, q: int, beta: float = 3.0, explore: float | None = None) -> DataFrame:
    """New assign after q hashed batches; q = 1 is synchronous."""
    return batched_with(edges, assign, settled(stats.cells(edges, assign)), blocks, seed, it, q, beta, explore)[0]


def packed(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """i, b, loop, near: a node's neighbours with their blocks and weights."""
    rows = node.incidence(edges).groupBy("i", "j").agg(F.sum("w_out").alias("o"), F.sum("w_in").alias("n")).join(assign.select(F.col("i").alias("j"), F.col("b").alias("t")), "j")
    near = rows.groupBy("i").agg(F.collect_list(F.struct("j", "t", "o", "n")).alias("near"))
    return assign.join(near, "i", "left").join(node.self_weights(edges), "i", "left").select("i", "b", F.coalesce("w_self", F.lit(0.0)).alias("loop"), "near")


def partition_local(edges: DataFrame, assign: DataFrame, blocks: int, seed: int, it: int, beta: float = 3.0, parts: int = 8, explore: float | None = None, counts: DataFrame | None = None) -> DataFrame:
    """Newest blocks within each of `parts` partitions (by a hash of the node, in a drawn order), one sweep old elsewhere.

    Each worker holds M, so it must be of a checked size: beyond it this schedule is refused, and batches are the way.
    """
    from blockpart.plans import local

    held = (stats.cells(edges, assign) if counts is None else counts).select("r", "s", "m").limit(HELD_CELLS + 1).collect()
    if len(held) > HELD_CELLS:
        raise ValueError("too many cells between blocks for this schedule: use batches")
    shared = edges.sparkSession.sparkContext.broadcast([tuple(r) for r in held])

    def run(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m, now = None, {}
        for pdf in pdfs:
            m = local.Sparse(shared.value, blocks) if m is None else m
            own = pdf["i"].tolist()
            now |= dict(zip(own, pdf["b"].tolist(), strict=True))
            for i, loop, near in zip(own, pdf["loop"].tolist(), pdf["near"], strict=True):
                known = sorted(((x["j"], now.get(x["j"], x["t"]), x["o"], x["n"]) for x in (near if near is not None else ())))
                local.visit(i, str(i), [x[1:] for x in known], loop, now, m, seed, it, beta, explore)
            yield pd.DataFrame({"i": own, "b": [now[i] for i in own]})

    rows = packed(edges, assign).withColumn("_turn", u01(seed, "order", it, F.col("i")))
    return rows.repartition(parts, "i").sortWithinPartitions("_turn", "i").select("i", "b", "loop", "near").mapInPandas(run, "i bigint, b bigint")


def sequential(edges: DataFrame, assign: DataFrame, blocks: int, seed: int, it: int, beta: float = 3.0, explore: float | None = None, counts: DataFrame | None = None) -> DataFrame:
    """One node after another, each with all earlier moves: a reference for graphs of a checked size, on arrays."""
    from blockpart.plans import local
    from blockpart.plans.search import to_local

    if assign.limit(SEQUENTIAL_NODES + 1).count() > SEQUENTIAL_NODES:
        raise ValueError("too many nodes for the sequential schedule")
    graph, own = to_local(edges, assign), dict(assign.select("i", "b").collect())
    import numpy as np

    b = local.sequential(graph, np.array([own[i] for i in graph.ids.tolist()]), blocks, seed, it, beta, explore)
    return edges.sparkSession.createDataFrame(list(zip(graph.ids.tolist(), b.tolist(), strict=True)), "i bigint, b bigint")


def converged(s_values: list[float], tau: float, window: int = 3) -> bool:
    """Whether the mean improvement of the last `window` sweeps is below tau of the objective."""
    return len(s_values) > window and (s_values[-1] - s_values[-1 - window]) / window < tau * abs(s_values[-1])
