"""The batch form: sparse matrices as (row, col, v) relations, products as joins and sums."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.functions.math import phi
from blockpart.operators import node
from blockpart.operators.stats import block_degrees

DENSE_LIMIT = 1_000_000


def indicator(assign: DataFrame) -> DataFrame:
    return assign.select(F.col("i").alias("row"), F.col("b").alias("col"), F.lit(1.0).alias("v"))


def adjacency(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("row"), F.col("dst").alias("col")).agg(F.sum("w").alias("v"))


def transpose(a: DataFrame) -> DataFrame:
    return a.select(F.col("col").alias("row"), F.col("row").alias("col"), "v")


def mul(a: DataFrame, b: DataFrame) -> DataFrame:
    left, right = a.toDF("row", "k", "x"), b.toDF("k", "col", "y")
    return left.join(right, "k").groupBy("row", "col").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def block_counts(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Gamma' A Gamma."""
    g = indicator(assign)
    return mul(transpose(g), mul(adjacency(edges), g))


def row_contrib(edges: DataFrame, assign: DataFrame) -> DataFrame:
    return mul(adjacency(edges), indicator(assign))


def col_contrib(edges: DataFrame, assign: DataFrame) -> DataFrame:
    return mul(transpose(adjacency(edges)), indicator(assign))


def tensor(proposals: DataFrame, edges: DataFrame, assign: DataFrame, counts: DataFrame, dense: bool = False, skip_same: bool = True) -> DataFrame:
    """Proposed counts of every node: only the differences (i, p, q, dm), or all N B B cells (i, p, q, m) for small graphs."""
    change = node.cell_delta(proposals, node.node_block(edges, assign), node.self_weights(edges))
    if not dense:
        return change
    rows = proposals.where("r <> s") if skip_same else proposals
    blocks = counts.select(F.col("r").alias("p")).union(counts.select("s")).distinct()
    if rows.count() * blocks.count() ** 2 > DENSE_LIMIT:
        raise ValueError("too large for the dense tensor")
    cube = rows.select("i").crossJoin(blocks).crossJoin(blocks.withColumnRenamed("p", "q"))
    full = cube.join(counts.select(F.col("r").alias("p"), F.col("s").alias("q"), "m"), ["p", "q"], "left").join(change, ["i", "p", "q"], "left")
    return full.select("i", "p", "q", (F.coalesce("m", F.lit(0.0)) + F.coalesce("dm", F.lit(0.0))).alias("m"))


def propose(edges: DataFrame, assign: DataFrame, counts: DataFrame, blocks: int) -> DataFrame:
    """row, col, v: the chance that node `row` proposes block `col`, for all nodes and blocks at once: the neighbour-pick matrix (a node's shares of blocks)
    times the block-pick matrix ((M + M' + 1) / (d + B)). Dense in the blocks, so of a checked size."""
    share = row_contrib(edges, assign).unionAll(col_contrib(edges, assign)).groupBy("row", "col").agg(F.sum("v").alias("v"))
    size = share.groupBy("row").agg(F.sum("v").alias("k"))
    if size.count() * blocks > DENSE_LIMIT:
        raise ValueError("too large for all chances of all nodes")
    pick = share.join(size, "row").select("row", "col", (F.col("v") / F.col("k")).alias("v"))
    both = node.symmetric(counts).select(F.col("u").alias("row"), F.col("t").alias("col"), F.col("m").alias("v"))
    every = counts.sparkSession.range(blocks).toDF("col")
    full = block_degrees(counts).select(F.col("t").alias("row"), "d").crossJoin(F.broadcast(every)).join(both, ["row", "col"], "left")
    return mul(pick, full.select("row", "col", ((F.coalesce("v", F.lit(0.0)) + 1) / (F.col("d") + blocks)).alias("v")))


def accept(proposals: DataFrame, edges: DataFrame, assign: DataFrame, counts: DataFrame, blocks: int, beta: float, seed: int, it: int) -> DataFrame:
    """i, r, s, a, accept of all nodes: changes of the objective by contraction of the difference tensor; the forward chance read from the matrix of proposals, the
    backward one from the same product over each node's proposed counts."""
    moving = proposals.where("r <> s").select("i", "r", "s")
    near, selfs = node.node_block(edges, assign), node.self_weights(edges)
    gain = node.delta_s(proposals, tensor(proposals, edges, assign, counts), counts, block_degrees(counts), near, selfs)
    ahead = propose(edges, assign, counts, blocks).select(F.col("row").alias("i"), F.col("col").alias("s"), F.col("v").alias("p_fwd"))
    cube = tensor(proposals, edges, assign, counts, dense=True)
    # Row r of the proposed counts in both directions, and degrees after the move, for each node.
    back = cube.join(moving.select("i", "r"), "i").select("i", "r", F.explode(F.array(
        F.struct(F.col("p").alias("t"), F.when(F.col("q") == F.col("r"), F.col("m")).otherwise(0.0).alias("m"), F.col("m").alias("d")),
        F.struct(F.col("q").alias("t"), F.when(F.col("p") == F.col("r"), F.col("m")).otherwise(0.0).alias("m"), F.col("m").alias("d")),
    )).alias("x")).groupBy("i", F.col("x.t").alias("t")).agg(F.sum("x.m").alias("m"), F.sum("x.d").alias("d"))
    share = node.node_weights(near, selfs, assign).join(moving, "i")
    loops = moving.join(selfs, "i")
    shift = loops.select("i", F.col("r").alias("t"), (-2 * F.col("w_self")).alias("k")).unionAll(loops.select("i", "s", 2 * F.col("w_self")))
    share = share.select("i", "t", "k").unionAll(shift).groupBy("i", "t").agg(F.sum("k").alias("k"))
    behind = share.join(back, ["i", "t"]).groupBy("i").agg((F.sum(F.col("k") * (F.col("m") + 1) / (F.col("d") + blocks)) / F.sum("k")).alias("p_bwd"))
    return node.decided(gain.join(ahead, ["i", "s"]).join(behind, "i"), beta, seed, it).select("i", "r", "s", "a", "accept")


def objective_of_tensor(dense: DataFrame) -> DataFrame:
    """i, s_val: the objective of each node's proposed counts, in full."""
    out = dense.groupBy("i", "p").agg(F.sum("m").alias("d")).select("i", (-phi(F.col("d"))).alias("x"))
    in_ = dense.groupBy("i", "q").agg(F.sum("m").alias("d")).select("i", (-phi(F.col("d"))).alias("x"))
    return dense.select("i", phi(F.col("m")).alias("x")).unionAll(out).unionAll(in_).groupBy("i").agg(F.sum("x").alias("s_val"))


def delta_by(proposals: DataFrame, edges: DataFrame, assign: DataFrame, counts: DataFrame, skip_same: bool = True, delta_only: bool = True, touched_only: bool = True) -> DataFrame:
    """i, d_s of the proposals under each shortcut setting; all settings agree, moves of no change have 0."""
    near, selfs = node.node_block(edges, assign), node.self_weights(edges)
    if not delta_only:
        from blockpart.operators.stats import log_posterior

        base = log_posterior(counts)
        found = objective_of_tensor(tensor(proposals, edges, assign, counts, dense=True, skip_same=skip_same)).join(F.broadcast(base.withColumnRenamed("s_val", "base"))).select("i", (F.col("s_val") - F.col("base")).alias("d_s"))
        return proposals.select("i").join(found, "i", "left").select("i", F.coalesce("d_s", F.lit(0.0)).alias("d_s"))
    change = node.cell_delta(proposals, near, selfs)
    if not touched_only:
        # Whole rows and columns of both blocks: untouched cells join with a change of zero.
        lines = proposals.where("r <> s").select("i", F.explode(F.array("r", "s")).alias("t"))
        whole = lines.join(counts.select(F.col("r").alias("t"), F.col("s").alias("q")), "t").select("i", F.col("t").alias("p"), "q").union(lines.join(counts.select("r", F.col("s").alias("t")), "t").select("i", "r", "t"))
        change = change.unionAll(whole.distinct().select("i", "p", "q", F.lit(0.0))).groupBy("i", "p", "q").agg(F.sum("dm").alias("dm"))
    found = node.delta_s(proposals, change, counts, block_degrees(counts), near, selfs).select("i", "d_s")
    return proposals.select("i").join(found, "i", "left").select("i", F.coalesce("d_s", F.lit(0.0)).alias("d_s"))
