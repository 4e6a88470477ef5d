"""Block merges: blocks as nodes of the block graph, scored from the counts alone, carried out greedily."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import u01
from blockpart.operators.node import gains, look_up, symmetric
from blockpart.operators.relops import settled
from blockpart.operators.stats import block_degrees, contract

#: Picks that the driver sorts and joins by itself; more go the distributed way.
DRIVER_PICKS = 5_000_000
#: Rows (of a pair of blocks and a block near its first) that are scored at a time: they are shuffled three times, some 90 bytes each in all.
PAIR_ROWS = 1 << 24
#: Blocks that one window numbers.
WINDOW_BLOCKS = 1_000_000


def as_graph(counts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The block graph: counts as edges, each block its own block."""
    edges = counts.select(F.col("r").alias("src"), F.col("s").alias("dst"), F.col("m").alias("w"))
    return edges, block_degrees(counts).select(F.col("t").alias("i"), F.col("t").alias("b"))


def all_pairs(counts: DataFrame) -> DataFrame:
    """Every adjacent pair, both ways: i = r, s."""
    pairs = counts.where("r <> s").select("r", "s")
    return pairs.union(pairs.select("s", "r")).distinct().select(F.col("r").alias("i"), "r", "s")


def propose(counts: DataFrame, blocks: int, tries: int, seed: int) -> DataFrame:
    """`tries` draws per block (with a key r:try), never of itself: via a neighbouring block, or uniform for blocks without one. The block graph is read once
    for each of both lookups, whatever the number of tries."""
    degrees, both = block_degrees(counts), symmetric(counts)
    near = both.where("u <> t")
    draw = lambda k: u01(seed, "prop", 0, F.col("i"), k)
    keyed = degrees.select(F.col("t").alias("r"), F.explode(F.sequence(F.lit(0), F.lit(tries - 1))).alias("k")).withColumn("i", F.concat_ws(":", "r", "k"))
    size = near.groupBy("u").agg(F.sum("m").alias("total")).withColumnRenamed("u", "r")
    first = look_up(keyed.join(size, "r", "left").select("i", F.col("r").alias("u"), (draw(0) * F.col("total")).alias("x")), near, blocks).withColumnRenamed("u", "r").withColumnRenamed("t", "u")
    drawn = first.join(degrees.select(F.col("t").alias("u"), "d"), "u", "left")
    drawn = drawn.withColumn("roam", F.col("u").isNull() | (draw(1) < F.lit(float(blocks)) / (F.col("d") + blocks)))
    found = look_up(drawn.select("i", "r", "u", "roam", F.when(~F.col("roam"), draw(3) * F.col("d")).alias("x")), both, blocks)
    uniform = F.least(F.floor(draw(2) * blocks), F.lit(blocks - 1)).cast("bigint")
    return found.select("r", F.when(F.col("roam"), uniform).otherwise(F.col("t")).alias("s")).where("r <> s").distinct()


def best_merges(counts: DataFrame, blocks: int, tries: int, seed: int) -> DataFrame:
    """The best of the draws of each block, written. Many rows are scored in portions of blocks, the shuffles of one portion being removed before the next."""
    pairs, spark = propose(counts, blocks, tries, seed), counts.sparkSession
    parts = -(-2 * tries * counts.count() // PAIR_ROWS)
    if parts <= 1:
        return settled(best_per_block(score(pairs, counts)))
    pairs, out = settled(pairs), None
    for k in range(parts):
        own = lambda c, k=k: F.pmod(F.xxhash64(c), F.lit(parts)) == k
        found = settled(best_per_block(score(pairs.where(own("r")), counts, own)))
        out = found if out is None else out.unionAll(found)
        spark._jvm.System.gc()
    return out


def score(pairs: DataFrame, counts: DataFrame, only: Callable[[str], Column] | None = None) -> DataFrame:
    """r, s, d_s of moving the whole of r into s: the block as a mover in the block graph. Pairs may share r, so each is a mover of its own. only: holds for the blocks r of all pairs, so that others need not be met."""
    moving = pairs.select("r", "s").distinct().select(F.struct("r", "s").alias("i"), F.col("r").alias("own"), "r", "s")
    zero = F.lit(0.0)
    near = counts.where("r <> s").select(F.col("r").alias("own"), F.col("s").alias("t"), F.col("m").alias("k_out"), zero.alias("k_in"), zero.alias("w_self"))
    near = near.unionAll(counts.where("r <> s").select("s", "r", zero, "m", zero)).unionAll(counts.where("r = s").select("r", "s", zero, zero, "m"))
    near = near if only is None else near.where(only("own"))
    near = near.groupBy("own", "t").agg(F.sum("k_out").alias("k_out"), F.sum("k_in").alias("k_in"), F.sum("w_self").alias("w_self"))
    return gains(moving, near, counts, block_degrees(counts), 1).select("r", "s", "d_s")


def best_per_block(scored: DataFrame) -> DataFrame:
    """The best merge of each block (to nine digits; ties to the least s)."""
    return scored.groupBy("r").agg(F.max_by(F.struct("s", "d_s"), F.struct(F.round("d_s", 9), -F.col("s"))).alias("x")).select("r", "x.s", "x.d_s")


def forest(picks: list[tuple[int, int, float]], excess: int) -> dict[int, int]:
    """Roots after the best `excess` merges that join two trees."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.get(x, x) != x:
            root[x] = root.get(root[x], root[x])
            x = root[x]
        return x

    for r, s, _ in sorted(picks, key=lambda p: (-round(p[2], 9), p[0], p[1])):
        if excess <= 0:
            break
        a, b = find(r), find(s)
        if a != b:
            root[max(a, b)] = min(a, b)
            excess -= 1
    return {x: find(x) for x in root}


def apply(picks: DataFrame, blocks: int, target: int) -> DataFrame:
    """merges(r, root) that leave `target` blocks, or as few as the picks allow."""
    spark = picks.sparkSession
    excess = blocks - target
    if picks.count() > DRIVER_PICKS:
        return apply_distributed(picks, excess)
    found = forest([tuple(r) for r in picks.select("r", "s", "d_s").collect()], excess)
    return spark.createDataFrame(sorted(found.items()), "r bigint, root bigint")


def apply_distributed(picks: DataFrame, excess: int) -> DataFrame:
    """The same count of merges without gathering the picks: the next best ones are contracted until enough blocks are gone."""
    from blockpart.operators.relops import components

    spark, used = picks.sparkSession, 0
    ranked = picks.select("r", "s", F.round("d_s", 9).alias("d")).orderBy(F.desc("d"), "r", "s")
    wanted, merges = excess, spark.createDataFrame([], "r bigint, root bigint")
    while wanted > 0:
        used += wanted
        found = components(ranked.limit(used).select(F.col("r").alias("src"), F.col("s").alias("dst"))).where("i <> root").select(F.col("i").alias("r"), "root")
        gone = found.count()
        if gone <= excess:
            merges = found
        if gone >= excess or used > picks.count():
            return merges
        wanted = excess - gone
    return merges


def numbering(assign: DataFrame, merges: DataFrame | None = None) -> DataFrame:
    """b, new: blocks, merges followed, numbered 0 .. B - 1 by their least node. One window below a checked size, beyond it a sort whose parts are counted."""
    blocks = assign.groupBy("b").agg(F.min("i").alias("least"))
    if merges is not None:
        blocks = blocks.join(merges.withColumnRenamed("r", "b"), "b", "left")
        blocks = settled(blocks.select("b", F.coalesce("root", "b").alias("root"), "least"))
        least = blocks.groupBy("root").agg(F.min("least").alias("least"))
    else:
        least = blocks = settled(blocks.withColumn("root", F.col("b")))
    least = least.select("root", "least")
    if least.count() <= WINDOW_BLOCKS:
        number = least.select("root", (F.row_number().over(Window.orderBy("least")) - 1).cast("bigint").alias("new"))
    else:
        number = ranked(least, "least").select("root", "new")
    return blocks.select("b", "root").join(number, "root").select("b", "new")


def ranked(rows: DataFrame, by: str) -> DataFrame:
    """Adds new: 0, 1, ... in the order of a column without ties. A range sort; only the sizes of its partitions reach the driver."""
    held = settled(rows.orderBy(by).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    sizes = sorted(map(tuple, held.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()))
    before, total = [], 0
    for p, n in sizes:
        before.append((p, total))
        total += n
    start = held.sparkSession.createDataFrame(before, "_p bigint, _n bigint")
    return held.withColumn("_p", part).join(F.broadcast(start), "_p").withColumn("new", F.col("_n") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_p", "_n", "_at")


def relabel(assign: DataFrame, merges: DataFrame | None = None) -> DataFrame:
    """Follow merges and number blocks 0 .. B - 1 by their least node."""
    return assign.join(numbering(assign, merges), "b").select("i", F.col("new").alias("b"))


def renumbered(counts: DataFrame, number: DataFrame) -> DataFrame:
    """Counts under new numbers of blocks (b, new), added up where blocks became one; edges are not read again."""
    return contract(counts, number.select(F.col("b").alias("r"), F.col("new").alias("root")))
