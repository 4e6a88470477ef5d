"""Counts between blocks, and the objective."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockpart.functions.math import h, phi


def cells(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """M: r, s, m. Edges are summed by (source's block, target) before the second join, so it moves less."""
    left = edges.join(assign.select(F.col("i").alias("src"), F.col("b").alias("r")), "src").groupBy("r", "dst").agg(F.sum("w").alias("w"))
    return left.join(assign.select(F.col("i").alias("dst"), F.col("b").alias("s")), "dst").groupBy("r", "s").agg(F.sum("w").alias("m"))


def block_degrees(counts: DataFrame) -> DataFrame:
    """t, d_out, d_in, d."""
    rows = counts.select(F.col("r").alias("t"), F.col("m").alias("o"), F.lit(0.0).alias("n")).unionAll(counts.select("s", F.lit(0.0), "m"))
    return rows.groupBy("t").agg(F.sum("o").alias("d_out"), F.sum("n").alias("d_in"), F.sum(F.col("o") + F.col("n")).alias("d"))


def contract(counts: DataFrame, merges: DataFrame) -> DataFrame:
    """Counts after blocks r became root; edges are not read again."""
    to = lambda c: merges.select(F.col("r").alias(c), F.col("root").alias(f"{c}_"))
    both = counts.join(to("r"), "r", "left").join(to("s"), "s", "left")
    return both.groupBy(F.coalesce("r_", "r").alias("r"), F.coalesce("s_", "s").alias("s")).agg(F.sum("m").alias("m"))


def add_edges(counts: DataFrame, new_edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Counts with the cells of new edges added."""
    return counts.unionByName(cells(new_edges, assign)).groupBy("r", "s").agg(F.sum("m").alias("m"))


def log_posterior(counts: DataFrame, degrees: DataFrame | None = None) -> DataFrame:
    """One row s_val: sum of phi(m) less the sums of phi of out and in degrees."""
    degrees = block_degrees(counts) if degrees is None else degrees
    parts = counts.select(phi(F.col("m")).alias("x")).unionAll(degrees.select(-phi(F.col("d_out")) - phi(F.col("d_in"))))
    return parts.agg(F.sum("x").alias("s_val"))


def undirected_counts(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """e_rs of an undirected graph: both directions, a self-edge twice."""
    return cells(edges.select("src", "dst", "w").unionAll(edges.select("dst", "src", "w")), assign)


def log_posterior_undirected(counts: DataFrame) -> DataFrame:
    """Half the sum of e ln(e / (e_r e_s)), for counts with both directions."""
    degrees = block_degrees(counts)
    parts = counts.select((0.5 * phi(F.col("m"))).alias("x")).unionAll(degrees.select(-phi(F.col("d_out"))))
    return parts.agg(F.sum("x").alias("s_val"))


def log_posterior_plain(counts: DataFrame, assign: DataFrame) -> DataFrame:
    """Without degree correction: sum of m ln(m / (n_r n_s))."""
    size = assign.groupBy("b").agg(F.count(F.lit(1)).cast("double").alias("n"))
    r, s = size.select(F.col("b").alias("r"), F.col("n").alias("n_r")), size.select(F.col("b").alias("s"), F.col("n").alias("n_s"))
    return counts.join(F.broadcast(r), "r").join(F.broadcast(s), "s").agg(F.sum(F.when(F.col("m") > 0, F.col("m") * F.ln(F.col("m") / (F.col("n_r") * F.col("n_s"))))).alias("s_val"))


def dl_terms(n: Column, e: Column, b: Column, s: Column, directed: bool = True) -> dict[str, Column]:
    """The three parts of the description length: block model, labels, data."""
    cells_ = b * b if directed else b * (b + 1) / 2
    return {"model": F.when(e > 0, e * h(cells_ / e)).otherwise(F.lit(0.0)), "labels": n * F.ln(F.greatest(b, F.lit(1.0))), "data": -s}


def description_length(counts: DataFrame, assign: DataFrame, directed: bool = True) -> DataFrame:
    """One row: n, e, b, s_val, model, labels, data, h_val."""
    size = assign.agg(F.count(F.lit(1)).cast("double").alias("n"), F.count_distinct("b").cast("double").alias("b"))
    weight = counts.agg((F.sum("m") * (1.0 if directed else 0.5)).alias("e"))
    s = log_posterior(counts) if directed else log_posterior_undirected(counts)
    row = size.join(F.broadcast(weight)).join(F.broadcast(s))
    parts = dl_terms(F.col("n"), F.col("e"), F.col("b"), F.col("s_val"), directed)
    return row.select("n", "e", "b", "s_val", *[c.alias(k) for k, c in parts.items()]).withColumn("h_val", F.col("model") + F.col("labels") + F.col("data"))
