"""Correctness of a partition against a truth, all from the contingency table (t, o, n)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.operators.relops import settled

#: Blocks on a side that the assignment solver takes.
ASSIGN_LIMIT = 2000


def contingency(truth: DataFrame, assign: DataFrame) -> DataFrame:
    """Nodes of known truth by truth block and output block."""
    return truth.where("t is not null").join(assign.select("i", F.col("b").alias("o")), "i").groupBy("t", "o").agg(F.count(F.lit(1)).alias("n"))


def with_totals(cont: DataFrame) -> DataFrame:
    return cont.cube("t", "o").agg(F.sum("n").alias("n"))


def hungarian(cost: np.ndarray) -> list[int]:
    """For each row of a square table its column in an assignment of least cost: shortest augmenting paths with potentials."""
    n = len(cost)
    u, v, match = np.zeros(n + 1), np.zeros(n + 1), np.full(n + 1, n, np.int64)
    for row in range(n):
        match[n], col = row, n
        least, before, used = np.full(n + 1, np.inf), np.full(n + 1, n, np.int64), np.zeros(n + 1, bool)
        while True:
            used[col] = True
            free = ~used[:n]
            reduced = cost[match[col]] - u[match[col]] - v[:n]
            closer = free & (reduced < least[:n])
            least[:n][closer], before[:n][closer] = reduced[closer], col
            nxt = int(np.where(free, least[:n], np.inf).argmin())
            step = least[nxt]
            u[match[used]] += step
            v[used] -= step
            least[:n][free] -= step
            col = nxt
            if match[col] == n:
                break
        while col != n:
            match[col] = match[before[col]]
            col = before[col]
    out = [0] * n
    for col in range(n):
        out[match[col]] = col
    return out


def association(cont: DataFrame) -> DataFrame:
    """t, o, n of the one-to-one association that matches most nodes."""
    rows = sorted(map(tuple, cont.select("t", "o", "n").collect()))
    ts, os = sorted({r[0] for r in rows}), sorted({r[1] for r in rows})
    if max(len(ts), len(os)) > ASSIGN_LIMIT:
        raise ValueError("too many blocks for the assignment on the driver")
    size = max(len(ts), len(os))
    gain = np.zeros((size, size))
    for t, o, n in rows:
        gain[ts.index(t), os.index(o)] = n
    found = [(ts[k], os[c], int(gain[k, c])) for k, c in enumerate(hungarian(-gain)[: len(ts)]) if c < len(os) and gain[k, c] > 0] if rows else []
    kinds = dict(cont.dtypes)
    return cont.sparkSession.createDataFrame(found, f"t {kinds['t']}, o {kinds['o']}, n bigint")


def accuracy(cont: DataFrame, matched: DataFrame) -> DataFrame:
    return matched.agg(F.sum("n").alias("matched")).join(cont.agg(F.sum("n").alias("total"))).select("matched", "total", (F.col("matched") / F.col("total")).alias("accuracy"))


def block_precision(cont: DataFrame, matched: DataFrame) -> DataFrame:
    """o, size, matched, precision; an output block without a partner has 0."""
    size = cont.groupBy("o").agg(F.sum("n").alias("size"))
    return size.join(matched.select("o", F.col("n").alias("matched")), "o", "left").select("o", "size", F.coalesce("matched", F.lit(0)).alias("matched")).withColumn("precision", F.col("matched") / F.col("size"))


def block_recall(cont: DataFrame, matched: DataFrame) -> DataFrame:
    size = cont.groupBy("t").agg(F.sum("n").alias("size"))
    return size.join(matched.select("t", F.col("n").alias("matched")), "t", "left").select("t", "size", F.coalesce("matched", F.lit(0)).alias("matched")).withColumn("recall", F.col("matched") / F.col("size"))


def _choose2(c):
    x = F.col(c).cast("double")
    return x * (x - 1) / 2


def pair_counts(cont: DataFrame) -> DataFrame:
    """c1 (together in both), c2 (apart in both), c3 (together in truth only), c4 (together in output only), in doubles."""
    same = cont.agg(F.sum(_choose2("n")).alias("c1"), F.sum("n").alias("n"))
    truth = cont.groupBy("t").agg(F.sum("n").alias("n")).agg(F.sum(_choose2("n")).alias("tt"))
    out = cont.groupBy("o").agg(F.sum("n").alias("n")).agg(F.sum(_choose2("n")).alias("oo"))
    row = same.join(truth).join(out)
    return row.select("c1", (_choose2("n") - F.col("tt") - F.col("oo") + F.col("c1")).alias("c2"), (F.col("tt") - F.col("c1")).alias("c3"), (F.col("oo") - F.col("c1")).alias("c4"), _choose2("n").alias("pairs"))


def _ratio(a, b):
    return F.when(b != 0, a / b)


def pair_measures(cont: DataFrame) -> DataFrame:
    """Pairwise precision and recall, Rand and adjusted Rand; null where undefined."""
    c1, c2, c3, c4, n = (F.col(x) for x in ("c1", "c2", "c3", "c4", "pairs"))
    expected = (c1 + c3) * (c1 + c4) / n
    top = (c1 + c3 + c1 + c4) / 2
    return pair_counts(cont).select(_ratio(c1, c1 + c4).alias("pair_precision"), _ratio(c1, c1 + c3).alias("pair_recall"), _ratio(c1 + c2, n).alias("rand"), F.when(n > 0, F.when(top != expected, (c1 - expected) / (top - expected)).otherwise(F.lit(1.0))).alias("adjusted_rand"))


def information(cont: DataFrame) -> DataFrame:
    """Entropies, mutual information (in bits) and information precision and recall."""
    total = cont.agg(F.sum("n").cast("double").alias("all"))
    margin = lambda c, a: cont.groupBy(c).agg(F.sum("n").alias(a))
    entropy = lambda c, a: margin(c, "n").join(F.broadcast(total)).agg((-F.sum(F.col("n") / F.col("all") * F.log2(F.col("n") / F.col("all")))).alias(a))
    joint = cont.join(margin("t", "nt"), "t").join(margin("o", "no"), "o").join(F.broadcast(total)).agg(F.sum(F.col("n") / F.col("all") * F.log2(F.col("n") * F.col("all") / (F.col("nt") * F.col("no")))).alias("information"))
    row = entropy("t", "h_truth").join(entropy("o", "h_output")).join(joint)
    share = lambda h, other: F.when(F.round(F.col(h), 12) > 0, F.col("information") / F.col(h)).when(F.round(F.col(other), 12) == 0, F.lit(1.0))
    return row.withColumn("info_precision", share("h_output", "h_truth")).withColumn("info_recall", share("h_truth", "h_output"))


def diagnosis(cont: DataFrame) -> DataFrame:
    """Numbers of blocks, and whether there are too many, too few or as many as in the truth."""
    row = cont.agg(F.count_distinct("t").alias("truths"), F.count_distinct("o").alias("outputs"))
    return row.withColumn("diagnosis", F.when(F.col("outputs") > F.col("truths"), "over").when(F.col("outputs") < F.col("truths"), "under").otherwise("equal"))


def report(truth: DataFrame, assign: DataFrame) -> DataFrame:
    """All measures in one row. The table of blocks is written, so that nodes are joined once and not for each measure."""
    cont = settled(contingency(truth, assign))
    return accuracy(cont, association(cont)).select("accuracy").join(pair_measures(cont)).join(information(cont)).join(diagnosis(cont))
