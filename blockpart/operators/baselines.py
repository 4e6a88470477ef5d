"""Methods to compare with: modularity (score, greedy, spectral, multislice), seed walks, trivial partitions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import u01
from blockpart.operators.relops import settled
from blockpart.operators.stats import block_degrees, cells


def modularity(edges: DataFrame, assign: DataFrame, gamma: float = 1.0) -> DataFrame:
    """One row q: sum over blocks of M_rr / E - gamma d_out d_in / E^2."""
    counts = cells(edges, assign)
    inner = counts.where("r = s").select(F.col("r").alias("t"), "m")
    total = counts.agg(F.sum("m").alias("e"))
    return block_degrees(counts).join(inner, "t", "left").join(F.broadcast(total)).agg(F.sum(F.coalesce("m", F.lit(0.0)) / F.col("e") - gamma * F.col("d_out") * F.col("d_in") / (F.col("e") * F.col("e"))).alias("q"))


def greedy_gains(edges: DataFrame, assign: DataFrame, gamma: float = 1.0) -> DataFrame:
    """i, s, dq: each node's best move of positive gain in modularity (ties to the least s)."""
    from blockpart.operators.node import node_block

    counts = cells(edges, assign)
    deg = block_degrees(counts)
    total = counts.agg(F.sum("m").alias("e"))
    size = edges.select(F.col("src").alias("i"), F.col("w").alias("o"), F.lit(0.0).alias("n")).unionAll(edges.select("dst", F.lit(0.0), "w")).groupBy("i").agg(F.sum("o").alias("o"), F.sum("n").alias("n"))
    rows = node_block(edges, assign).withColumn("k", F.col("k_out") + F.col("k_in")).join(assign.select("i", F.col("b").alias("r")), "i").join(size, "i").join(deg.select("t", "d_out", "d_in"), "t").join(F.broadcast(total))
    own = F.col("t") == F.col("r")
    pull = F.col("k") / F.col("e") - gamma * (F.col("o") * (F.col("d_in") - F.when(own, F.col("n")).otherwise(0.0)) + F.col("n") * (F.col("d_out") - F.when(own, F.col("o")).otherwise(0.0))) / (F.col("e") * F.col("e"))
    rows = rows.select("i", "t", "r", "o", "n", "e", pull.alias("pull"))
    base = assign.select("i", F.col("b").alias("t")).join(size, "i").join(deg.select("t", "d_out", "d_in"), "t").join(F.broadcast(total)).select("i", (-gamma * (F.col("o") * (F.col("d_in") - F.col("n")) + F.col("n") * (F.col("d_out") - F.col("o"))) / (F.col("e") * F.col("e"))).alias("alone"))
    stay = rows.where("t = r").select("i", F.col("pull").alias("stay"))
    gains = rows.where("t <> r").join(stay, "i", "left").join(base, "i").select("i", F.col("t").alias("s"), F.round(F.col("pull") - F.coalesce("stay", "alone"), 12).alias("dq"))
    rank = Window.partitionBy("i").orderBy(F.desc("dq"), "s")
    return gains.where("dq > 0").withColumn("k", F.row_number().over(rank)).where("k = 1").select("i", "s", "dq")


def greedy(edges: DataFrame, nodes: DataFrame, gamma: float = 1.0, passes: int = 10, seed: int = 42) -> DataFrame:
    """assign by repeated local moves (a hashed half of the nodes at a time), then blocks as nodes, while modularity grows."""
    assign = settled(nodes.select("i", F.col("i").alias("b")))
    level, nodes_of = edges, assign
    best = modularity(edges, assign, gamma).first()[0] or 0.0
    for it in range(passes):
        part = nodes_of.select(F.col("i"), F.col("b"))
        for turn in range(6):
            moves = greedy_gains(level, part, gamma).where(u01(seed, "batch", it * 10 + turn, F.col("i")) < 0.5)
            part = settled(part.join(moves.select("i", "s"), "i", "left").select("i", F.coalesce("s", "b").alias("b")))
        new = settled(assign.join(part.toDF("b", "b2"), "b").select("i", F.col("b2").alias("b")))
        q = modularity(edges, new, gamma).first()[0] or 0.0
        if q <= best + 1e-9:
            return assign
        assign, best = new, q
        level = settled(cells(edges, assign).select(F.col("r").alias("src"), F.col("s").alias("dst"), F.col("m").alias("w")))
        nodes_of = assign.select(F.col("b").alias("i")).distinct().select("i", F.col("i").alias("b"))
    return assign


def power_step(edges: DataFrame, vector: DataFrame) -> DataFrame:
    """i, x: the symmetrised modularity matrix times vector(i, x); the rank-one part is two numbers."""
    both = edges.select("src", "dst", (F.col("w") / 2).alias("w")).unionAll(edges.select("dst", "src", F.col("w") / 2))
    deg = both.groupBy(F.col("src").alias("i")).agg(F.sum("w").alias("k"))
    total = deg.join(vector, "i").agg(F.sum("k").alias("e"), F.sum(F.col("k") * F.col("x")).alias("kx"))
    spread = both.join(vector.toDF("dst", "x"), "dst").groupBy(F.col("src").alias("i")).agg(F.sum(F.col("w") * F.col("x")).alias("ax"))
    return deg.join(spread, "i").join(F.broadcast(total)).select("i", (F.col("ax") - F.col("k") * F.col("kx") / F.col("e")).alias("x"))


def spectral(edges: DataFrame, rounds: int = 15, seed: int = 42, levels: int = 20) -> DataFrame:
    """assign by splits in two, all blocks of a level at once, by the sign of the leading eigenvector of each block's own modularity matrix (shifted power
    iteration); a block is split only if that gains modularity, and a level without gain ends it."""
    nodes = settled(edges.select(F.col("src").alias("i")).union(edges.select("dst")).distinct())
    both = settled(edges.select("src", "dst", (F.col("w") / 2).alias("w")).unionAll(edges.select("dst", "src", F.col("w") / 2)))
    deg = settled(both.groupBy(F.col("src").alias("i")).agg(F.sum("w").alias("k")))
    e = deg.agg(F.sum("k")).first()[0] or 1.0
    assign = settled(nodes.select("i", F.lit(0).cast("bigint").alias("b")))
    closed = assign.sparkSession.createDataFrame([], "b bigint")
    for level in range(levels):
        live = settled(assign.join(closed, "b", "left_anti").join(deg, "i"))
        inner = both.join(live.select(F.col("i").alias("src"), "b"), "src").join(live.select(F.col("i").alias("dst"), F.col("b").alias("b2")), "dst").where("b = b2").select("src", "dst", "w")
        inner = settled(inner)
        # What a node has within its block beyond expectation is taken off its diagonal.
        size = live.groupBy("b").agg(F.sum("k").alias("d"))
        own = inner.groupBy(F.col("src").alias("i")).agg(F.sum("w").alias("own"))
        rows = live.join(size, "b").join(own, "i", "left").select("i", "b", "k", (F.coalesce("own", F.lit(0.0)) - F.col("k") * F.col("d") / e).alias("off"))
        rows = settled(rows)
        shift = rows.agg(F.max("k")).first()[0] or 0.0
        x = rows.select("i", "b", "k", "off", (u01(seed, "batch", level, F.col("i")) - 0.5).alias("x"))
        for _ in range(rounds):
            pull = x.groupBy("b").agg(F.sum(F.col("k") * F.col("x")).alias("kx"))
            spread = inner.join(x.select(F.col("i").alias("dst"), "x"), "dst").groupBy(F.col("src").alias("i")).agg(F.sum(F.col("w") * F.col("x")).alias("ax"))
            y = x.join(spread, "i", "left").join(pull, "b")
            y = settled(y.select("i", "b", "k", "off", (F.coalesce("ax", F.lit(0.0)) - F.col("k") * F.col("kx") / e - F.col("off") * F.col("x") + shift * F.col("x")).alias("x")))
            norm = y.groupBy("b").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
            x = y.join(norm, "b").select("i", "b", "k", "off", F.when(F.col("norm") > 0, F.col("x") / F.col("norm")).otherwise(F.col("x")).alias("x"))
        side = settled(x.select("i", "b", "k", F.when(F.col("x") > 0, 1).otherwise(0).cast("bigint").alias("side")))
        # Gain of each block's split: what it cuts against what the degrees of both sides expect.
        cut = inner.join(side.select(F.col("i").alias("src"), "b", F.col("side").alias("s1")), "src").join(side.select(F.col("i").alias("dst"), F.col("side").alias("s2")), "dst")
        cut = cut.where("s1 <> s2").groupBy("b").agg(F.sum("w").alias("cut"))
        halves = side.groupBy("b").agg(F.sum(F.when(F.col("side") == 1, F.col("k")).otherwise(0.0)).alias("d1"), F.sum(F.when(F.col("side") == 0, F.col("k")).otherwise(0.0)).alias("d0"))
        gain = halves.join(cut, "b", "left").select("b", ((2 * F.col("d1") * F.col("d0") / e - F.coalesce("cut", F.lit(0.0))) / e).alias("gain"))
        good = settled(gain.where("gain > 1e-9").select("b"))
        if good.isEmpty():
            break
        closed = settled(assign.select("b").distinct().join(good, "b", "left_anti").select((2 * F.col("b")).alias("b")))
        split = side.join(good, "b").select("i", "side")
        assign = settled(assign.join(split, "i", "left").select("i", (2 * F.col("b") + F.coalesce("side", F.lit(0))).alias("b")))
    from blockpart.operators.merge import relabel

    return relabel(assign)


def multislice(edges: DataFrame, assign: DataFrame, gamma: float = 1.0, coupling: float = 0.1) -> DataFrame:
    """One row q of edges(src, dst, w, slice) and assign(i, slice, b): null terms per slice, and a coupling of a node's copies in neighbouring slices."""
    own = assign.select(F.col("i").alias("src"), "slice", F.col("b").alias("r"))
    counts = edges.join(own, ["src", "slice"]).join(assign.select(F.col("i").alias("dst"), "slice", F.col("b").alias("s")), ["dst", "slice"]).groupBy("slice", "r", "s").agg(F.sum("w").alias("m"))
    inner = counts.where("r = s").agg(F.sum("m").alias("inner"))
    deg = counts.select("slice", F.col("r").alias("t"), F.col("m").alias("o"), F.lit(0.0).alias("n")).unionAll(counts.select("slice", "s", F.lit(0.0), "m")).groupBy("slice", "t").agg(F.sum("o").alias("o"), F.sum("n").alias("n"))
    e = counts.groupBy("slice").agg(F.sum("m").alias("e"))
    null = deg.join(e, "slice").agg(F.sum(F.col("o") * F.col("n") / F.col("e")).alias("null_"))
    pairs = assign.join(assign.select("i", (F.col("slice") - 1).alias("slice"), F.col("b").alias("b2")), ["i", "slice"])
    links = pairs.agg(F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum(F.when(F.col("b") == F.col("b2"), 1).otherwise(0)), F.lit(0)).alias("kept"))
    total = e.agg(F.sum("e").alias("all"))
    return inner.join(null).join(links).join(total).select(((F.col("inner") - gamma * F.col("null_") + coupling * F.col("kept")) / (F.col("all") + coupling * F.col("pairs"))).alias("q"))


def seed_walk(edges: DataFrame, cues: DataFrame, damping: float = 0.85, steps: int = 5) -> DataFrame:
    """i, score: a walk that returns to the cue nodes."""
    out = edges.groupBy("src").agg(F.sum("w").alias("k"))
    step = settled(edges.join(out, "src").select("src", "dst", (F.col("w") / F.col("k")).alias("p")))
    n = cues.count()
    home = cues.select("i", F.lit((1 - damping) / n).alias("score"))
    now = cues.select("i", F.lit(1.0 / n).alias("score"))
    for _ in range(steps):
        sent = now.join(step, now["i"] == step["src"]).groupBy(F.col("dst").alias("i")).agg((damping * F.sum(F.col("score") * F.col("p"))).alias("score"))
        now = settled(sent.unionAll(home).groupBy("i").agg(F.sum("score").alias("score")))
    return now


def trivial(nodes: DataFrame, seed: int = 42) -> dict[str, DataFrame]:
    return {"one": nodes.select("i", F.lit(0).cast("bigint").alias("b")), "alone": nodes.select("i", F.col("i").alias("b")), "random": nodes.select("i", F.floor(u01(seed, "batch", 0, F.col("i")) * 5).cast("bigint").alias("b"))}


def cliques(sizes: list[int], links: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """Adjacency of cliques with single links between first nodes, both ways; and the clique of each node."""
    n = sum(sizes)
    a, at, own = np.zeros((n, n)), np.cumsum([0, *sizes]), np.repeat(np.arange(len(sizes)), sizes)
    for k, size in enumerate(sizes):
        a[at[k] : at[k] + size, at[k] : at[k] + size] = 1 - np.eye(size)
    for x, y in links:
        i, j = at[x] + (1 if len(sizes) > 3 else 0), at[y]
        a[i, j] = a[j, i] = 1
    return a, own
