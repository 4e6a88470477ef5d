"""The search over numbers of blocks: bracket by halving, then golden section; each try merges down and sweeps.

One search, two engines with the same draws, rules and numbers: on Spark every vector is a written table and the driver keeps scalars; a graph below a
checked size may run on arrays instead, with the same result: on the driver, or, from DRIVER_EDGES and DRIVER_NODES on, in one task of an executor.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.operators import merge, stats
from blockpart.operators.relops import few_sent, forget, passing, settled
from blockpart.plans import local, sweep


@dataclass
class FitConfig:
    beta: float = 3.0
    explore: float | None = None
    proposals: int = 10
    rate: float = 0.5
    tau_open: float = 5e-4
    tau_closed: float = 1e-4
    window: int = 3
    max_sweeps: int = 100
    #: sync (one sweep old; where blocks are small all may move at once, so damp it), batched (q batches), local (newest within a partition; Spark only), sequential (newest).
    schedule: str = "batched"
    q: int = 4
    parts: int = 8
    damp: float = 1.0
    directed: bool = True
    seed: int = 42
    restarts: int = 1
    #: spark, local, or auto: local for graphs of up to LOCAL_EDGES and LOCAL_NODES.
    engine: str = "auto"
    #: A number of blocks to look around first (twice, once and half of it), as after an earlier stage.
    around: int | None = None

    @property
    def batches(self) -> int:
        return self.q if self.schedule == "batched" else 1

    @property
    def step_beta(self) -> float:
        """Undirected graphs stand in both directions, where a move changes the objective twice as much."""
        return self.beta if self.directed else self.beta / 2


def next_try(history: list[tuple[int, float]], rate: float = 0.5) -> int | None:
    """The next number of blocks, None at the end: halving (at this rate) until the length grows, then the wider side at 0.382."""
    tried = sorted({b: h for b, h in history}.items())
    low_b, least = min(tried, key=lambda x: (x[1], x[0]))
    at = [b for b, _ in tried].index(low_b)
    if at == 0:
        return None if low_b <= 1 else max(1, min(low_b - 1, int(low_b * (1 - rate))))
    below = tried[at - 1][0]
    above = tried[at + 1][0] if at + 1 < len(tried) else low_b
    if max(above - low_b, low_b - below) <= 1:
        return None
    if above - low_b >= low_b - below:
        step = max(1, round(0.382 * (above - low_b)))
        return min(low_b + step, above - 1)
    return max(low_b - max(1, round(0.382 * (low_b - below))), below + 1)


def explored(engine, cfg: FitConfig, start=None) -> tuple[object, list[dict]]:
    """The state of least length, and the history. A try is looked for by its target, but stands with the number of blocks that it has: sweeps may empty some."""
    state, sweeps = engine.start(start), 0
    if start is not None:  # a partition from elsewhere is a sample to go on from; nodes alone are not
        state, sweeps = engine.settle(state, cfg.tau_open)
    blocks = engine.blocks(state)
    s, h = engine.length(state)
    history = [{"target": blocks, "B": blocks, "h_val": h, "s_val": s, "sweeps": sweeps}]
    found, best = {blocks: state}, state
    first = [] if cfg.around is None else [b for b in (2 * cfg.around, cfg.around, max(1, cfg.around // 2)) if b < blocks]
    while (target := first.pop(0) if first else next_try([(x["target"], x["h_val"]) for x in history], cfg.rate)) is not None:
        state = engine.shrink(found[min(x for x in found if x >= target)], target)
        closed = any(x["target"] < target for x in history)
        state, sweeps = engine.settle(state, cfg.tau_closed if closed else cfg.tau_open)
        blocks = engine.blocks(state)
        s, h = engine.length(state)
        row = {"target": target, "B": blocks, "h_val": h, "s_val": s, "sweeps": sweeps}
        if (round(h, 9), blocks) < min((round(x["h_val"], 9), x["B"]) for x in history):
            best = state
        if blocks not in found or h < min(x["h_val"] for x in history if x["B"] == blocks):
            found[blocks] = state
        history.append(row)
    return best, history


def to_local(edges: DataFrame, nodes: DataFrame) -> local.Graph:
    """A small graph as arrays."""
    ids = np.array(sorted(r[0] for r in nodes.select("i").distinct().collect()), np.int64)
    rows = edges.groupBy("src", "dst").agg(F.sum("w").alias("w")).orderBy("src", "dst").toPandas()
    return local.Graph(ids, np.searchsorted(ids, rows["src"].to_numpy(np.int64)), np.searchsorted(ids, rows["dst"].to_numpy(np.int64)), rows["w"].to_numpy(float))


def endpoints(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("i")).union(edges.select("dst")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """An undirected graph, each pair once, in both directions; a self-edge counts twice."""
    rows = edges.select("src", "dst", "w")
    return rows.unionAll(rows.select("dst", "src", "w"))


def best_of(runs: list[tuple[object, list[dict]]]) -> tuple[object, list[dict]]:
    return min(runs, key=lambda run: min((round(x["h_val"], 9), x["B"]) for x in run[1]))


def on_arrays(graph: local.Graph, cfg: FitConfig, given: np.ndarray | None, helped: bool = False) -> tuple[np.ndarray, list[dict]]:
    runs = []
    for own in (replace(cfg, seed=cfg.seed + k) for k in range(cfg.restarts)):
        with local.LocalEngine(graph, own, own.seed, helped) as engine:
            runs.append(explored(engine, own, given))
    return best_of(runs)


def in_task(edges: DataFrame, nodes: DataFrame, cfg: FitConfig, start: DataFrame | None) -> tuple[DataFrame, list[dict]]:
    """The array engine in one task of an executor: edges and nodes stream to it from files, blocks and history go to a file, and the driver holds neither."""
    edges = settled(edges.groupBy("src", "dst").agg(F.sum("w").cast("double").alias("w")))
    nodes = nodes.select("i", F.col("i").alias("b")) if start is None else nodes.select("i").join(start.select("i", "b"), "i", "left")
    nodes = settled(nodes.distinct())
    rows = edges.select("src", "dst", "w", F.lit(None).cast("bigint").alias("b")).unionAll(nodes.select("i", "i", F.lit(None).cast("double"), "b"))
    cold = start is None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = pa.Table.from_batches(list(batches), pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("w", pa.float64()), ("b", pa.int64())]))
        given, rest = held.filter(held["w"].is_null()).sort_by("src"), held.filter(held["w"].is_valid())
        if given["b"].null_count:
            raise ValueError("nodes without a block to start from")
        ids, b = given["src"].to_numpy(), given["b"].to_numpy()
        graph = local.Graph(ids, np.searchsorted(ids, rest["src"].to_numpy()), np.searchsorted(ids, rest["dst"].to_numpy()), rest["w"].to_numpy())
        del held, given, rest
        best, history = on_arrays(graph, cfg, None if cold else b, len(graph.src) >= local.HELPED)
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([None], pa.int64()), pa.array([json.dumps(history)])], ["i", "b", "history"])
        for low in range(0, len(ids), 100_000):
            own, to = ids[low : low + 100_000], best[low : low + 100_000].astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(to), pa.nulls(len(own), pa.string())], ["i", "b", "history"])

    found = settled(rows.coalesce(1).mapInArrow(run, "i bigint, b bigint, history string"))
    return found.where("history is null").select("i", "b"), json.loads(found.where("history is not null").first()["history"])


def fit(edges: DataFrame, nodes: DataFrame | None = None, cfg: FitConfig | None = None, start: DataFrame | None = None) -> tuple[DataFrame, list[dict]]:
    """assign(i, b) of least description length, and the history; of `restarts` runs with other seeds the best."""
    cfg = cfg or FitConfig()
    edges = settled(edges.select("src", "dst", "w"))
    nodes = endpoints(edges) if nodes is None else nodes.select("i").distinct()
    engine, size = cfg.engine, (edges.count(), nodes.count())
    if engine == "auto":
        small = cfg.schedule != "local" and size[0] * (1 if cfg.directed else 2) <= local.LOCAL_EDGES and size[1] <= local.LOCAL_NODES
        engine = "local" if small else "spark"
    if not cfg.directed:
        edges = both_ways(edges)
    spark = edges.sparkSession
    if engine == "local" and (size[0] > local.DRIVER_EDGES or size[1] > local.DRIVER_NODES):
        return in_task(edges, nodes, cfg, start)
    if engine == "local":
        graph = to_local(edges, nodes)
        given = None
        if start is not None:
            own = dict(start.select("i", "b").collect())
            given = np.array([own[i] for i in graph.ids.tolist()])
        best, history = on_arrays(graph, cfg, given)
        return spark.createDataFrame(list(zip(graph.ids.tolist(), best.tolist(), strict=True)), "i bigint, b bigint"), history
    with few_sent(spark):
        graph, nodes = settled(edges.groupBy("src", "dst").agg(F.sum("w").alias("w"))), settled(nodes)
        best, history = best_of([explored(SparkEngine(graph, nodes, own), own, start) for own in (replace(cfg, seed=cfg.seed + k) for k in range(cfg.restarts))])
    return best.assign, history


@dataclass
class State:
    """Partition and counts as written tables, and the number of blocks."""

    assign: DataFrame
    counts: DataFrame
    blocks: int


class SparkEngine:
    def __init__(self, edges: DataFrame, nodes: DataFrame, cfg: FitConfig):
        self.edges, self.nodes, self.cfg, self.n = edges, nodes, cfg, nodes.count()
        self.many = edges.count() > local.DRIVER_EDGES
        if cfg.schedule not in ("sync", "batched", "local", "sequential"):
            raise ValueError(f"no schedule {cfg.schedule}")

    def start(self, given: DataFrame | None) -> State:
        assign = settled(merge.relabel(self.nodes.select("i", F.col("i").alias("b")) if given is None else given.select("i", "b")))
        return State(assign, settled(stats.cells(self.edges, assign)), assign.agg(F.max("b")).first()[0] + 1)

    def blocks(self, state: State) -> int:
        return state.blocks

    def renumbered(self, state: State, merges: DataFrame | None) -> State:
        with passing(self.edges.sparkSession) as keep:
            number = settled(merge.numbering(state.assign, merges))
            assign, counts = settled(state.assign.join(number, "b").select("i", F.col("new").alias("b"))), settled(merge.renumbered(state.counts, number))
            blocks = number.agg(F.max("new")).first()[0] + 1
            keep(assign, counts)
        return State(assign, counts, blocks)

    def left(self, state: State, first: State) -> None:
        """The tables of a state that is gone on from are removed, but for the first, which is its caller's; the shuffles of its plans are removed once the driver's collector meets them, which many rows should not wait for."""
        if state is not first:
            forget(self.edges.sparkSession, state.assign._settled_at, state.counts._settled_at)
        if self.many:
            self.edges.sparkSession._jvm.System.gc()

    def shrink(self, state: State, target: int) -> State:
        """Counts come from the counts before; edges are not read."""
        first = state
        while state.blocks > target:
            with passing(self.edges.sparkSession) as keep:
                picks = merge.best_merges(state.counts, state.blocks, self.cfg.proposals, self.cfg.seed + state.blocks)
                merges = merge.apply(picks, state.blocks, target)
                if merges.isEmpty():  # no draw led to another block
                    merges = merges.sparkSession.createDataFrame([(1, 0)], "r bigint, root bigint")
                after = self.renumbered(state, merges)
                keep(after.assign, after.counts)
            self.left(state, first)
            state = after
        return state

    def settle(self, state: State, tau: float) -> tuple[State, int]:
        """Sweeps until they improve too little; counts are kept up from moved edges, and one number a sweep reaches the driver."""
        cfg, past, sweeps, first = self.cfg, [stats.log_posterior(state.counts).first()[0]], 0, state
        while sweeps < cfg.max_sweeps and not sweep.converged(past, tau, cfg.window):
            with passing(self.edges.sparkSession) as keep:
                assign, counts = sweep.swept(self.edges, state.assign, state.counts, state.blocks, cfg, sweeps)
                keep(assign, counts)
            self.left(state, first)
            state = State(assign, counts, state.blocks)
            past.append(stats.log_posterior(counts).first()[0])
            sweeps += 1
        after = self.renumbered(state, None)
        self.left(state, first)
        return after, sweeps

    def length(self, state: State) -> tuple[float, float]:
        half = 1.0 if self.cfg.directed else 0.5
        s, e = stats.log_posterior(state.counts).first()[0], state.counts.agg(F.sum("m")).first()[0]
        s, e, b = half * (s or 0.0), half * (e or 0.0), state.blocks
        size = b * b if self.cfg.directed else b * (b + 1) / 2
        return s, (e * local.h(size / e) if e else 0.0) + self.n * float(np.log(max(b, 1))) - s
