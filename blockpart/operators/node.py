"""One update of all nodes at once: neighbourhood, proposal, change of the objective, correction, decision, refresh."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import phi, u01
from blockpart.operators.relops import settled
from blockpart.operators.stats import block_degrees

#: Blocks of a chunk of running weights; and so few blocks that a draw may meet all of them.
CHUNK, FEW = 65_536, 64


def self_weights(edges: DataFrame) -> DataFrame:
    return edges.where("src = dst").groupBy(F.col("src").alias("i")).agg(F.sum("w").alias("w_self"))


def incidence(edges: DataFrame) -> DataFrame:
    other = edges.where("src <> dst")
    return other.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.col("w").alias("w_out"), F.lit(0.0).alias("w_in")).unionAll(other.select("dst", "src", F.lit(0.0), "w"))


def node_block(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """i, t, k_out, k_in: weight between a node and a block; self-edges kept apart."""
    return incidence(edges).join(assign.select(F.col("i").alias("j"), F.col("b").alias("t")), "j").groupBy("i", "t").agg(F.sum("w_out").alias("k_out"), F.sum("w_in").alias("k_in"))


def node_weights(near: DataFrame, selfs: DataFrame, assign: DataFrame) -> DataFrame:
    """i, t, k: both directions, twice the self-edge at the node's own block."""
    own = selfs.join(assign, "i").select("i", F.col("b").alias("t"), (2 * F.col("w_self")).alias("k"))
    return near.select("i", "t", (F.col("k_out") + F.col("k_in")).alias("k")).unionAll(own).groupBy("i", "t").agg(F.sum("k").alias("k"))


def neighbourhood(edges: DataFrame, assign: DataFrame, only: Column | None = None) -> DataFrame:
    """i, t, k_out, k_in, w_self: node_block and self-edges (at the node's own block) in one pass; of all nodes i or those that `only` holds for, which filters the edges before they are joined."""
    loop, zero = F.col("src") == F.col("dst"), F.lit(0.0)
    out = edges.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.when(loop, zero).otherwise(F.col("w")).alias("o"), zero.alias("n"), F.when(loop, F.col("w")).otherwise(zero).alias("l"))
    rows = out.unionAll(edges.where(~loop).select("dst", "src", zero, "w", zero))
    rows = rows if only is None else rows.where(only)
    return rows.join(assign.select(F.col("i").alias("j"), F.col("b").alias("t")), "j").groupBy("i", "t").agg(F.sum("o").alias("k_out"), F.sum("n").alias("k_in"), F.sum("l").alias("w_self"))


def neighbour_block(weights: DataFrame, seed: int, it: int) -> DataFrame:
    """i, u: a block in proportion to the node's weight with it. Each of its blocks draws a waiting time of that rate and the first wins: one aggregate with partial
    sums, so a node with very many blocks is no single task's."""
    wait = -F.ln(1 - u01(seed, "prop", it, F.concat_ws(":", "i", "t"), 0)) / F.col("k")
    return weights.groupBy("i").agg(F.min_by("t", F.struct(wait, F.col("t"))).alias("u"))


def steps(both: DataFrame, blocks: int) -> DataFrame:
    """u, t, low, high, cell: running weights of both(u, t, m) within u. With very many blocks they run in chunks of t, so that no task sorts a whole large one; and each
    row stands in the cells (as many as u has rows, of equal width) that its range meets, two on average. Few blocks have one cell."""
    over = Window.partitionBy("u")
    upto = Window.unboundedPreceding, 0
    if blocks <= FEW:
        rows = both.withColumn("high", F.sum("m").over(over.orderBy("t").rowsBetween(*upto)))
        return rows.select("u", "t", (F.col("high") - F.col("m")).alias("low"), "high", F.lit(0).cast("bigint").alias("cell"))
    if blocks <= CHUNK:
        rows = both.select("u", "t", "m", F.sum("m").over(over.orderBy("t").rowsBetween(*upto)).alias("high"), F.sum("m").over(over).alias("total"), F.count(F.lit(1)).over(over).alias("n"))
    else:
        part = both.withColumn("chunk", F.floor(F.col("t") / CHUNK))
        tops = part.groupBy("u", "chunk").agg(F.sum("m").alias("mc"), F.count(F.lit(1)).alias("nc"))
        tops = tops.select("u", "chunk", (F.sum("mc").over(over.orderBy("chunk").rowsBetween(*upto)) - F.col("mc")).alias("base"), F.sum("mc").over(over).alias("total"), F.sum("nc").over(over).alias("n"))
        rows = part.join(tops, ["u", "chunk"]).withColumn("high", F.col("base") + F.sum("m").over(Window.partitionBy("u", "chunk").orderBy("t").rowsBetween(*upto)))
    rows = rows.withColumn("low", F.col("high") - F.col("m"))
    cell = lambda x: F.floor(F.col(x) * F.col("n") / F.col("total"))
    return rows.select("u", "t", "low", "high", F.explode(F.sequence(cell("low"), cell("high"))).alias("cell"))


def look_up(draws: DataFrame, both: DataFrame, blocks: int) -> DataFrame:
    """draws(u, x, ...) and t, the block of u in whose range of running weights x lies; x is below the total of u, or null, which finds none."""
    if blocks <= FEW:
        placed = draws.withColumn("cell", F.when(F.col("x").isNotNull(), F.lit(0).cast("bigint")))
    else:
        sizes = both.groupBy("u").agg(F.sum("m").alias("total"), F.count(F.lit(1)).alias("n"))
        placed = draws.join(sizes, "u", "left").withColumn("cell", F.floor(F.col("x") * F.col("n") / F.col("total"))).drop("n", "total")
    table = steps(both, blocks).withColumnsRenamed({"u": "_u", "cell": "_cell"})
    here = (F.col("u") == F.col("_u")) & (F.col("cell") == F.col("_cell")) & (F.col("low") <= F.col("x")) & (F.col("x") < F.col("high"))
    return placed.join(table, here, "left").drop("_u", "_cell", "low", "high", "cell", "x")


def symmetric(counts: DataFrame) -> DataFrame:
    """u, t, m: counts in both directions together."""
    return counts.select(F.col("r").alias("u"), F.col("s").alias("t"), "m").unionAll(counts.select("s", "r", "m")).groupBy("u", "t").agg(F.sum("m").alias("m"))


def propose(weights: DataFrame, assign: DataFrame, counts: DataFrame, degrees: DataFrame, blocks: int, seed: int, it: int, explore: float | None = None) -> DataFrame:
    """i, r, u, s, kind. A uniform block with probability B / (d_u + B) (or `explore`), else one by its weight with u. Blocks must be 0 .. blocks - 1."""
    picked = neighbour_block(weights, seed, it).join(assign.select("i", F.col("b").alias("r")), "i").join(degrees.select(F.col("t").alias("u"), "d"), "u")
    draw = lambda k: u01(seed, "prop", it, F.col("i"), k)
    chance = F.lit(float(blocks)) / (F.col("d") + blocks) if explore is None else F.lit(explore)
    picked = picked.withColumn("roam", draw(1) < chance).withColumn("x", F.when(~F.col("roam"), draw(3) * F.col("d")))
    found = look_up(picked.select("i", "r", "u", "roam", "x"), symmetric(counts), blocks)
    uniform = F.least(F.floor(draw(2) * blocks), F.lit(blocks - 1)).cast("bigint")
    kind = F.when(F.col("roam"), "uniform").otherwise("neighbour")
    return found.select("i", "r", "u", F.when(F.col("roam"), uniform).otherwise(F.col("t")).alias("s"), kind.alias("kind"))


def cell_delta(proposals: DataFrame, near: DataFrame, selfs: DataFrame) -> DataFrame:
    """i, p, q, dm: what each move (r to s) would change in M; proposals of the same block are left out first."""
    moving = proposals.where("r <> s").select("i", "r", "s")
    x = lambda p, q, v: F.struct(F.col(p).alias("p"), F.col(q).alias("q"), v.alias("dm"))
    rows = moving.join(near, "i").select("i", F.explode(F.array(x("r", "t", -F.col("k_out")), x("s", "t", F.col("k_out")), x("t", "r", -F.col("k_in")), x("t", "s", F.col("k_in")))).alias("c"))
    own = moving.join(selfs, "i").select("i", F.explode(F.array(x("r", "r", -F.col("w_self")), x("s", "s", F.col("w_self")))).alias("c"))
    return rows.unionAll(own).select("i", "c.*").groupBy("i", "p", "q").agg(F.sum("dm").alias("dm")).where("dm <> 0")


def delta_s(proposals: DataFrame, change: DataFrame, counts: DataFrame, degrees: DataFrame, near: DataFrame, selfs: DataFrame) -> DataFrame:
    """i, r, s, k_out, k_in (with the self-edge), d_s: only touched cells and four degrees are read."""
    moving = proposals.where("r <> s").select("i", "r", "s")
    touched = change.join(counts.select(F.col("r").alias("p"), F.col("s").alias("q"), "m"), ["p", "q"], "left").withColumn("m", F.coalesce("m", F.lit(0.0)))
    part = touched.groupBy("i").agg(F.sum(phi(F.col("m") + F.col("dm")) - phi(F.col("m"))).alias("cells_"))
    size = near.groupBy("i").agg(F.sum("k_out").alias("o"), F.sum("k_in").alias("n")).join(selfs, "i", "full").select("i", *[(F.coalesce(c, F.lit(0.0)) + F.coalesce("w_self", F.lit(0.0))).alias(a) for c, a in (("o", "k_out"), ("n", "k_in"))])
    end = lambda c: degrees.select(F.col("t").alias(c), F.col("d_out").alias(f"{c}_o"), F.col("d_in").alias(f"{c}_i"))
    rows = moving.join(size, "i").join(end("r"), "r").join(end("s"), "s").join(part, "i", "left")
    gain = lambda d, k: phi(F.col(d) + k) - phi(F.col(d))
    ends = gain("r_o", -F.col("k_out")) + gain("s_o", F.col("k_out")) + gain("r_i", -F.col("k_in")) + gain("s_i", F.col("k_in"))
    return rows.select("i", "r", "s", "k_out", "k_in", (F.coalesce("cells_", F.lit(0.0)) - ends).alias("d_s"))


def hastings(moves: DataFrame, change: DataFrame, counts: DataFrame, degrees: DataFrame, weights: DataFrame, selfs: DataFrame, blocks: int) -> DataFrame:
    """i, p_fwd, p_bwd: chances to propose the move and, after it, to propose it back."""
    both = symmetric(counts)
    near = weights.join(moves.select("i", "r", "s", "k_out", "k_in"), "i").join(selfs, "i", "left").withColumn("w_self", F.coalesce("w_self", F.lit(0.0)))
    total = near.groupBy("i").agg(F.sum("k").alias("k_i"))
    deg = degrees.select("t", "d")
    ahead = near.join(both.select("t", F.col("u").alias("s"), "m"), ["t", "s"], "left").join(deg, "t").groupBy("i").agg(F.sum(F.col("k") * (F.coalesce("m", F.lit(0.0)) + 1) / (F.col("d") + blocks)).alias("f"))
    # Backwards the node's own self weight is at s, and counts and degrees are those after the move.
    x = lambda t, k: F.struct(F.col(t).alias("t"), k.alias("k"))
    moved = near.groupBy("i", "r", "s", "k_out", "k_in", "w_self").agg(F.collect_list(F.struct("t", "k")).alias("own")).withColumn("own", F.concat("own", F.array(x("r", -2 * F.col("w_self")), x("s", 2 * F.col("w_self"))))).select("i", "r", "s", "k_out", "k_in", F.explode("own").alias("e")).select("i", "r", "s", "k_out", "k_in", "e.*").groupBy("i", "r", "s", "k_out", "k_in", "t").agg(F.sum("k").alias("k")).where("k <> 0")
    shift = change.select("i", F.col("p").alias("t"), F.col("q").alias("r"), "dm").unionAll(change.select("i", F.col("q").alias("t"), F.col("p").alias("r"), "dm")).groupBy("i", "t", "r").agg(F.sum("dm").alias("dm"))
    weight = F.col("k_out") + F.col("k_in")
    after = F.col("d") - F.when(F.col("t") == F.col("r"), weight).otherwise(0.0) + F.when(F.col("t") == F.col("s"), weight).otherwise(0.0)
    back = moved.join(both.select("t", F.col("u").alias("r"), "m"), ["t", "r"], "left").join(shift, ["i", "t", "r"], "left").join(deg, "t").groupBy("i").agg(F.sum(F.col("k") * (F.coalesce("m", F.lit(0.0)) + F.coalesce("dm", F.lit(0.0)) + 1) / (after + blocks)).alias("g"))
    return total.join(ahead, "i").join(back, "i").select("i", (F.col("f") / F.col("k_i")).alias("p_fwd"), (F.col("g") / F.col("k_i")).alias("p_bwd"))


def decide(moves: DataFrame, chances: DataFrame, beta: float, seed: int, it: int) -> DataFrame:
    """Adds p_fwd, p_bwd, a, draw, accept."""
    return decided(moves.join(chances, "i"), beta, seed, it)


def gains(moving: DataFrame, near: DataFrame, counts: DataFrame, degrees: DataFrame, blocks: int) -> DataFrame:
    """i, r, s, k_out, k_in (with the self-edge), d_s, p_fwd, p_bwd of moving(i, own, r, s), by near(own, t, k_out, k_in, w_self).

    The closed form of cell_delta, delta_s and hastings together: a row for each block near a mover, two lookups of M and one of the degrees, one aggregate.
    """
    both = counts.select(F.col("r").alias("u"), "s", F.col("m").alias("o"), F.lit(0.0).alias("n")).unionAll(counts.select("s", "r", F.lit(0.0), "m")).groupBy("u", "s").agg(F.sum("o").alias("o"), F.sum("n").alias("n"))
    at = lambda block, o, n: both.select(F.col("u").alias(block), F.col("s").alias("t"), F.col("o").alias(o), F.col("n").alias(n))
    zero, r, s, t = F.lit(0.0), F.col("r"), F.col("s"), F.col("t")
    # Rows for r and s themselves, which need not be near.
    ends = moving.select("i", "r", "s", F.explode(F.array("r", "s")).alias("t"), zero.alias("k_out"), zero.alias("k_in"), zero.alias("w_self"))
    rows = moving.join(near, "own").select("i", "r", "s", "t", "k_out", "k_in", "w_self").unionAll(ends)
    rows = rows.join(at("r", "a", "b"), ["r", "t"], "left").join(at("s", "c", "e"), ["s", "t"], "left").join(degrees.select("t", "d_out", "d_in", "d"), "t", "left").fillna(0.0, ["a", "b", "c", "e", "d_out", "d_in", "d"])
    ko, ki, w = F.col("k_out"), F.col("k_in"), F.col("w_self")
    a, b, c, e, d = (F.col(x) for x in "abced")
    step = lambda m, x: phi(m + x) - phi(m)
    far = (t != r) & (t != s)
    of = lambda x, block, how, name: how(F.when(t == block, x)).alias(name)
    out = rows.groupBy("i", "r", "s").agg(
        F.sum(F.when(far, step(a, -ko) + step(b, -ki) + step(c, ko) + step(e, ki)).otherwise(zero)).alias("g"),
        F.sum((ko + ki + 2 * w) * (c + e + 1) / (d + blocks)).alias("f"),
        F.sum(F.when(far, (ko + ki) * (a + b - ko - ki + 1) / (d + blocks)).otherwise(zero)).alias("h"),
        F.sum(ko).alias("o"), F.sum(ki).alias("n"), F.sum(w).alias("w"),
        of(a, r, F.max, "rr"), of(c, r, F.max, "sr"), of(a, s, F.max, "rs"), of(c, s, F.max, "ss"),
        of(ko, r, F.sum, "or_"), of(ki, r, F.sum, "nr"), of(ko, s, F.sum, "os"), of(ki, s, F.sum, "ns"),
        of(F.col("d_out"), r, F.max, "dor"), of(F.col("d_in"), r, F.max, "dir"), of(F.col("d_out"), s, F.max, "dos"), of(F.col("d_in"), s, F.max, "dis"),
    )
    x = {k: F.col(k) for k in out.columns}
    k_out, k_in, weight = x["o"] + x["w"], x["n"] + x["w"], x["o"] + x["n"] + 2 * x["w"]
    rr, ss, rs, sr = -x["or_"] - x["nr"] - x["w"], x["os"] + x["ns"] + x["w"], x["nr"] - x["os"], x["or_"] - x["ns"]
    corners = step(x["rr"], rr) + step(x["ss"], ss) + step(x["rs"], rs) + step(x["sr"], sr)
    sides = step(x["dor"], -k_out) + step(x["dos"], k_out) + step(x["dir"], -k_in) + step(x["dis"], k_in)
    share = lambda part: F.when(weight > 0, part / weight)
    back = x["h"] + (x["or_"] + x["nr"]) * (2 * (x["rr"] + rr) + 1) / (x["dor"] + x["dir"] - weight + blocks)
    back = back + (x["os"] + x["ns"] + 2 * x["w"]) * (x["rs"] + rs + x["sr"] + sr + 1) / (x["dos"] + x["dis"] + weight + blocks)
    return out.select("i", "r", "s", k_out.alias("k_out"), k_in.alias("k_in"), (x["g"] + corners - sides).alias("d_s"), share(x["f"]).alias("p_fwd"), share(back).alias("p_bwd"))


def decided(moves: DataFrame, beta: float, seed: int, it: int) -> DataFrame:
    """Adds a, draw, accept to moves with d_s, p_fwd, p_bwd."""
    a = F.least(F.lit(1.0), F.exp(F.greatest(F.lit(-700.0), F.least(F.lit(700.0), beta * F.round("d_s", 9)))) * F.col("p_bwd") / F.col("p_fwd"))
    return moves.withColumn("a", F.round(a, 9)).withColumn("draw", u01(seed, "acc", it, F.col("i"))).withColumn("accept", F.col("draw") < F.col("a"))


def evaluate(edges: DataFrame, assign: DataFrame, counts: DataFrame, blocks: int, seed: int, it: int, beta: float = 3.0, explore: float | None = None, only: Column | None = None) -> DataFrame:
    """The whole step: every node's proposal and decision against the same counts. Three written tables."""
    near, degrees = settled(neighbourhood(edges, assign, only)), block_degrees(counts)
    weights = near.select("i", "t", (F.col("k_out") + F.col("k_in") + 2 * F.col("w_self")).alias("k"))
    proposals = propose(weights, assign, counts, degrees, blocks, seed, it, explore)
    moving = settled(proposals.where("r <> s").select("i", F.col("i").alias("own"), "r", "s"))
    return settled(decided(gains(moving, near.withColumnRenamed("i", "own"), counts, degrees, blocks), beta, seed, it))


def apply_moves(assign: DataFrame, decided: DataFrame) -> DataFrame:
    return assign.join(decided.where("accept").select("i", "s"), "i", "left").select("i", F.coalesce("s", "b").alias("b"))


def refresh_cells(counts: DataFrame, edges: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
    """Counts after a sweep from edges with a moved end, each taken out of its old cell and put into its new one. The moved nodes filter the edges before those are joined."""
    both = before.join(after.withColumnRenamed("b", "b2"), "i")
    moved = both.where("b <> b2").select("i")
    end = lambda c: moved.select(F.col("i").alias(c), F.lit(True).alias(f"{c}_moved"))
    near = edges.select("src", "dst", "w").join(end("src"), "src", "left").join(end("dst"), "dst", "left").where("src_moved or dst_moved")
    near = near.join(both.toDF("src", "r", "r2"), "src").join(both.toDF("dst", "s", "s2"), "dst")
    cell = lambda r, s, v: F.struct(F.col(r).alias("r"), F.col(s).alias("s"), v.alias("m"))
    change = near.select(F.explode(F.array(cell("r", "s", -F.col("w")), cell("r2", "s2", F.col("w")))).alias("c")).select("c.*")
    return counts.select("r", "s", "m").unionAll(change).groupBy("r", "s").agg(F.sum("m").alias("m")).where("m <> 0")


def influence(edges: DataFrame, moved: DataFrame) -> DataFrame:
    """Mean number of distinct neighbours, and the share of linked pairs whose ends both moved."""
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct()
    m = moved.select("i", F.lit(1).alias("m"))
    both = pairs.join(m.toDF("x", "mx"), "x", "left").join(m.toDF("y", "my"), "y", "left")
    ends = pairs.select("x").unionAll(pairs.select("y"))
    return both.agg(F.count(F.lit(1)).alias("pairs"), F.sum(F.when(F.col("mx").isNotNull() & F.col("my").isNotNull(), 1).otherwise(0)).alias("together")).join(ends.agg((F.count(F.lit(1)) / F.count_distinct("x")).alias("mean_neighbours")))
