"""Planted graphs: degree-corrected, Poisson edge weights, with knobs for overlap, sizes and hubs; and hybrids with real graphs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import u01
from blockpart.operators.relops import by_weight, counted, settled, weight_cells

#: The four panels: blocks, within/between strength, Dirichlet alpha, power-law exponent, largest theta.
PRESETS = {"base": (5, 25.0, 10, 2.5, 30.0), "overlap": (5, 8.0, 10, 2.5, 30.0), "sizes": (5, 25.0, 2, 2.5, 30.0), "hubs": (5, 25.0, 10, 2.05, 100.0)}
DEGREE = 16.0
#: Pairs of a task that draws for each.
PAIRS_A_TASK = 4_000_000


def theta_powerlaw(nodes: DataFrame, exponent: float, lo: float = 1.0, hi: float = 30.0, seed: int = 42) -> DataFrame:
    """i, theta: bounded power law by its inverse distribution, to nine digits."""
    e = 1.0 - exponent
    x = u01(seed, "theta", 0, F.col("i"))
    return nodes.select("i", F.round(F.pow((hi**e - lo**e) * x + F.lit(lo**e), F.lit(1.0 / e)), 9).alias("theta"))


def shares_dirichlet(spark: SparkSession, blocks: int, alpha: int, seed: int = 42) -> DataFrame:
    """b, low, high: cumulative block shares; each block sums alpha exponential draws."""
    rows = spark.range(blocks).select(F.col("id").alias("b"), F.explode(F.sequence(F.lit(0), F.lit(alpha - 1))).alias("k"))
    own = rows.groupBy("b").agg(F.round(F.sum(-F.ln(1 - u01(seed, "dir", 0, F.col("b"), F.col("k").cast("string")))), 9).alias("x"))
    run = Window.orderBy("b")  # a row per block
    own = own.withColumn("top", F.sum("x").over(run.rowsBetween(Window.unboundedPreceding, 0))).withColumn("all", F.sum("x").over(Window.partitionBy()))
    return own.select("b", F.round((F.col("top") - F.col("x")) / F.col("all"), 9).alias("low"), F.round(F.col("top") / F.col("all"), 9).alias("high"))


def truth_dirichlet(nodes: DataFrame, blocks: int, alpha: int, seed: int = 42) -> DataFrame:
    shares = shares_dirichlet(nodes.sparkSession, blocks, alpha, seed)
    x = nodes.select("i", u01(seed, "blk", 0, F.col("i")).alias("x"))
    return x.join(F.broadcast(shares), (F.col("x") >= F.col("low")) & (F.col("x") < F.col("high"))).select("i", F.col("b").alias("t"))


def omega(spark: SparkSession, blocks: int, within: float, between: float = 1.0) -> DataFrame:
    r, s = spark.range(blocks).toDF("r"), spark.range(blocks).toDF("s")
    return r.crossJoin(s).select("r", "s", F.when(F.col("r") == F.col("s"), within).otherwise(between).cast("double").alias("v"))


def poisson_count(x: Column, rate: Column, most: int = 12) -> Column:
    """The number of k with CDF(k) <= x: `most` terms in a row, and all further ones only where the draw is beyond them."""
    term, cdf, out = F.exp(-rate), None, F.lit(0)
    for k in range(most):
        term = term if k == 0 else term * rate / k
        cdf = term if cdf is None else cdf + term
        out = out + F.when(F.round(cdf, 12) <= x, 1).otherwise(0)
    # Terms by their logarithms, as exp(-rate) may be too small; far enough that the CDF is 1 to 12 digits.
    end = F.ceil(rate + 12 * F.sqrt(rate) + 40).cast("int")
    start = F.struct((-rate).alias("ln"), F.exp(-rate).alias("cdf"), F.when(F.round(F.exp(-rate), 12) <= x, 1).otherwise(0).alias("n"))

    def step(acc: Column, k: Column) -> Column:
        ln = acc["ln"] + F.ln(rate) - F.ln(k.cast("double"))
        total = acc["cdf"] + F.exp(ln)
        return F.struct(ln.alias("ln"), total.alias("cdf"), (acc["n"] + F.when(F.round(total, 12) <= x, 1).otherwise(0)).alias("n"))

    return F.when(F.round(cdf, 12) <= x, F.aggregate(F.sequence(F.lit(1), end), start, step, lambda acc: acc["n"])).otherwise(out)


def planted(truth: DataFrame, theta: DataFrame, strength: DataFrame, mean_degree: float = DEGREE, seed: int = 42, method: str = "blockpair") -> DataFrame:
    """edges(src, dst, w) of the model. 'pairwise': a draw per ordered pair, all of them; 'blockpair': totals per block pair, then ends in proportion to theta."""
    nodes = settled(truth.hint("merge").join(theta, "i"))  # rows of ids are small in files and not in memory: never sent through the driver
    size = nodes.groupBy("t").agg(F.sum("theta").alias("theta"))
    pairs = strength.join(F.broadcast(size.toDF("r", "tr")), "r").join(F.broadcast(size.toDF("s", "ts")), "s").withColumn("load", F.col("v") * F.col("tr") * F.col("ts"))
    n, load = nodes.count(), pairs.agg(F.sum("load")).first()[0]
    scale = n * mean_degree / load
    if method == "pairwise":
        a, b = nodes.toDF("src", "r", "ta").repartition(max(1, n * n // PAIRS_A_TASK), "src"), nodes.toDF("dst", "s", "tb")
        rows = a.crossJoin(b).join(F.broadcast(strength), ["r", "s"])
        raw, x = F.lit(round(scale, 12)) * F.col("v") * F.col("ta") * F.col("tb"), u01(seed, "pois", 0, F.concat_ws(":", "src", "dst"))
        # Most pairs draw nothing, which is told before anything is rounded; the margin is wider than what rounding does.
        some = settled(rows.where(x + 1e-8 >= F.exp(-raw)).select("src", "dst", F.round(raw, 9).alias("rate"), x.alias("x")))
        return some.select("src", "dst", poisson_count(F.col("x"), F.col("rate")).cast("double").alias("w")).where("w > 0")
    draw = np.random.default_rng(seed)
    totals = [(r["r"], r["s"], int(draw.poisson(scale * r["load"])), r["tr"], r["ts"]) for r in pairs.orderBy("r", "s").collect()]
    rows = nodes.sparkSession.createDataFrame(totals, "r bigint, s bigint, n bigint, tr double, ts double").where("n > 0")
    rows = counted(rows, F.lit(1).cast("bigint"), F.col("n"), "k")
    ident = F.concat_ws(":", "r", "s", "k")
    rows = rows.select("r", "s", (u01(seed, "end", 0, ident, 0) * F.col("tr")).alias("xr"), (u01(seed, "end", 0, ident, 1) * F.col("ts")).alias("xs"))
    cells = weight_cells(nodes, "t", "i", "theta")
    both = by_weight(by_weight(rows, "r", "xr", cells, "src"), "s", "xs", cells, "dst")
    return both.groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))


def preset(nodes: DataFrame, name: str = "base", blocks: int | None = None, seed: int = 42, method: str = "blockpair", degree: float = DEGREE) -> tuple[DataFrame, DataFrame]:
    """Edges and truth of a panel on these nodes."""
    b, ratio, alpha, exponent, hi = PRESETS[name]
    b = blocks or b
    truth = truth_dirichlet(nodes, b, alpha, seed)
    return planted(truth, theta_powerlaw(nodes, exponent, 1.0, hi, seed), omega(nodes.sparkSession, b, ratio), degree, seed, method), truth


def symmetrise(edges: DataFrame) -> DataFrame:
    """Each undirected pair once, weights of both directions summed."""
    return edges.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.sum("w").alias("w"))


def binarise(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").distinct().withColumn("w", F.lit(1.0))


def degrees(edges: DataFrame) -> DataFrame:
    """i, k_out, k_in, neighbours."""
    rows = edges.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.col("w").alias("o"), F.lit(0.0).alias("n")).unionAll(edges.select("dst", "src", F.lit(0.0), "w"))
    return rows.groupBy("i").agg(F.sum("o").alias("k_out"), F.sum("n").alias("k_in"), F.count_distinct("j").alias("neighbours"))


def embed(real: DataFrame, made: DataFrame, share: float = 0.05, seed: int = 42) -> DataFrame:
    """Hybrid: both graphs (ids 4 key + kind apart) and cross edges by the product of degrees; adds part.

    Cross edges are drawn one by one: the k-th takes an end in each graph in proportion to degree.
    """
    a, b = degrees(real).select("i", (F.col("k_out") + F.col("k_in")).alias("k")), degrees(made).select("i", (F.col("k_out") + F.col("k_in")).alias("k"))
    e = min(real.agg(F.sum("w")).first()[0] or 0, made.agg(F.sum("w")).first()[0] or 0)
    draws = real.sparkSession.range(int(share * e)).toDF("n")

    def end(frame: DataFrame, nodes: DataFrame, name: str, k: int) -> DataFrame:
        """Cumulative degrees within hashed groups: first a group, then a node of it."""
        grouped = nodes.withColumn("g", F.pmod(F.xxhash64("i"), F.lit(256)))
        tops = grouped.groupBy("g").agg(F.sum("k").alias("kg")).withColumn("hg", F.sum("kg").over(Window.orderBy("g").rowsBetween(Window.unboundedPreceding, 0))).withColumn("all", F.sum("kg").over(Window.partitionBy()))
        x = frame.join(F.broadcast(tops.withColumn("lg", F.col("hg") - F.col("kg"))), (u01(seed, "cross", 0, F.col("n"), k) * F.col("all") >= F.col("lg")) & (u01(seed, "cross", 0, F.col("n"), k) * F.col("all") < F.col("hg"))).withColumn("y", u01(seed, "cross", 0, F.col("n"), k) * F.col("all") - F.col("lg"))
        return by_weight(x.drop("kg", "hg", "lg", "all"), "g", "y", weight_cells(grouped, "g", "i", "k"), name).drop("g")

    cross = end(end(draws, a, "x", 0), b, "y_", 1)
    turn = u01(seed, "cross", 0, F.col("n"), 2) < 0.5
    cross = cross.select(F.when(turn, F.col("x")).otherwise(F.col("y_")).alias("src"), F.when(turn, F.col("y_")).otherwise(F.col("x")).alias("dst")).groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))
    return real.select("src", "dst", "w", F.lit("real").alias("part")).unionAll(made.select("src", "dst", "w", F.lit("gen"))).unionAll(cross.select("src", "dst", "w", F.lit("cross")))
