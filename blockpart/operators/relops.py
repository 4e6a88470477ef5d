"""Relational helpers around the methods: as-of and interval joins, rings, components, packed maps, differences of stages."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

_OWN: dict[str, str] = {}
#: Of each thread, the tables written in each open scope of `passing`.
_SCOPES = threading.local()
#: Bytes of a table, in files or as shuffled, that a join may send through the driver while `few_sent` holds.
SENT = 1 << 20


def scratch_path(spark: SparkSession, kind: str = "settled") -> str:
    """A fresh name in the shared folder that the session names; in a private folder only where none is named, in local mode."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and spark.sparkContext.master.startswith("local"):
        if "dir" not in _OWN:
            _OWN["dir"] = tempfile.mkdtemp(prefix="blockpart-")
            atexit.register(shutil.rmtree, _OWN["dir"], ignore_errors=True)
        base = f"file://{_OWN['dir']}"
    return f"{(base or spark.conf.get('spark.sql.warehouse.dir')).rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def settled(df: DataFrame) -> DataFrame:
    """Written to the shared folder and read back: cuts the lineage and survives lost executors."""
    path = scratch_path(df.sparkSession)
    for scope in _SCOPES.__dict__.get("open", [])[-1:]:
        scope.append(path)
    df.write.parquet(path)
    found = df.sparkSession.read.schema(df.schema).parquet(path)
    found._settled_at = path
    return found


def forget(spark: SparkSession, *paths: str) -> None:
    """Remove written tables that nothing reads any more."""
    for path in paths:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


@contextlib.contextmanager
def passing(spark: SparkSession) -> Iterator[Callable[..., None]]:
    """What this thread settles within it is removed at its end, but for the settled tables that are handed to the function it gives; those stay with the scope around it, if any."""
    scopes = _SCOPES.__dict__.setdefault("open", [])
    written, kept = [], set()
    scopes.append(written)
    try:
        yield lambda *frames: kept.update(x.__dict__["_settled_at"] for x in frames)
    finally:
        scopes.pop()
        for scope in scopes[-1:]:
            scope.extend(x for x in written if x in kept)
        forget(spark, *(x for x in written if x not in kept))


@contextlib.contextmanager
def few_sent(spark: SparkSession) -> Iterator[None]:
    """Within it, joins send only tables of up to SENT bytes through the driver: a row a node is a few bytes in files and many times that as a hash table, of which the
    driver holds several at a time. Tables of few blocks are still sent, as their keys are too few to be dealt out by."""
    names = ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")
    was = {k: spark.conf.get(k, None) for k in names}
    most = int(spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold())
    try:
        for k in names:
            spark.conf.set(k, str(min(most, SENT)))
        yield
    finally:
        for k, v in was.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def in_parts(rows: DataFrame, *by: str) -> DataFrame:
    """Written in the order of `by`, with _part, the range of rows that a row is in, and _at, its place. Ranges are cut by rows, so a hot key spans many."""
    held = rows.repartitionByRange(*by).sortWithinPartitions(*by).withColumn("_at", F.monotonically_increasing_id())
    return settled(held).withColumn("_part", F.shiftright("_at", 33))


def running(held: DataFrame, key: str, value: str, name: str) -> DataFrame:
    """Adds `name` to rows of `in_parts` in an order led by `key`: the sum of `value` within `key` up to and with each row; sums within ranges, raised by those of the ranges before."""
    own = Window.partitionBy(key, "_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, 0)
    earlier = Window.partitionBy(key).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row per range
    starts = held.groupBy(key, "_part").agg(F.sum(value).alias("_sum")).select(key, "_part", F.coalesce(F.sum("_sum").over(earlier), F.lit(0.0)).alias("_start"))
    found = held.withColumn(name, F.sum(value).over(own)).join(starts, [key, "_part"])
    return found.withColumn(name, F.col(name) + F.col("_start")).drop("_at", "_part", "_start")


def counted(df: DataFrame, low: Column, high: Column, name: str, chunk: int = 1 << 16) -> DataFrame:
    """A row for each whole number from low to high, in two steps, so that no row holds a long array and no task all numbers of one row."""
    chunks = df.withColumn("_low", low).withColumn("_high", high).withColumn("_k", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("_high") - F.col("_low")) / chunk))))
    first = F.col("_low") + F.col("_k") * chunk
    # By number, as rows of chunks are few and small: else they are put together again, and one task makes all.
    return chunks.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "_low", "_high", "_k").withColumn(name, F.explode(F.sequence(first, F.least(first + (chunk - 1), F.col("_high"))))).drop("_low", "_high", "_k")


def weight_cells(nodes: DataFrame, key: str, node: str, weight: str) -> tuple[DataFrame, DataFrame]:
    """For `by_weight`: the sum and number of the nodes of each key, and the nodes' ranges of running weights (in the order of `node`) in as many cells as the key has nodes."""
    held = in_parts(nodes.select(F.col(key).alias("_key"), F.col(node).alias("_node"), F.col(weight).cast("double").alias("_w")), "_key", "_node")
    cell = lambda c: F.floor(c * F.col("_n") / F.col("_total"))
    sizes = held.groupBy("_key").agg(F.sum("_w").alias("_total"), F.count(F.lit(1)).alias("_n"))
    steps = running(held, "_key", "_w", "_to").withColumn("_from", F.col("_to") - F.col("_w")).join(F.broadcast(sizes), "_key")
    return sizes, counted(steps.drop("_w"), cell(F.col("_from")), cell(F.col("_to")), "_cell").drop("_n", "_total")


def by_weight(draws: DataFrame, key: str, x: str, cells: tuple[DataFrame, DataFrame], name: str) -> DataFrame:
    """Draws with `name`: the node of the same key in whose range of running weights x lies; x is from 0 to below the key's sum, and goes. A draw meets the nodes of one cell, about one, whatever their number."""
    sizes, steps = cells
    placed = draws.withColumn("_key", F.col(key)).join(F.broadcast(sizes), "_key").withColumn("_cell", F.floor(F.col(x) * F.col("_n") / F.col("_total"))).drop("_n", "_total")
    found = placed.join(steps.hint("merge"), ["_key", "_cell"]).where((F.col("_from") <= F.col(x)) & (F.col(x) < F.col("_to")))
    return found.drop("_key", "_cell", "_from", "_to", x).withColumnRenamed("_node", name)


def as_of_join(left: DataFrame, right: DataFrame, by: str, t: str, value: str) -> DataFrame:
    """Each left row with the latest right value at or before its time: one union, ranges of its order, and what each range is left by the ones before.

    Right rows without a key or a time match nothing, nor do left rows without a key.
    """
    right = right.where(F.col(by).isNotNull() & F.col(t).isNotNull())
    rows = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1)).unionByName(right.select(by, t, F.col(value).alias("_v")).withColumn("_side", F.lit(0)), allowMissingColumns=True)
    held = in_parts(rows, by, t, "_side")
    own = Window.partitionBy(by, "_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, 0)
    earlier = Window.partitionBy(by).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row per range
    last = held.groupBy(by, "_part").agg(F.max_by("_v", F.when(F.col("_v").isNotNull(), F.col("_at"))).alias("_last"))
    last = last.select(by, "_part", F.last("_last", ignorenulls=True).over(earlier).alias("_last"))
    found = held.withColumn("_v", F.last("_v", ignorenulls=True).over(own)).where("_side = 1").join(last, [by, "_part"], "left")
    return found.select(*[f"`{c}`" for c in left.columns if c != value], F.coalesce("_v", "_last").alias(value))


def interval_join(a: DataFrame, b: DataFrame, by: str, t: str, seconds: int) -> DataFrame:
    """Pairs of equal `by` whose times differ by at most `seconds`: b's rows stand in three buckets of that width."""
    second = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    left = a.withColumn("_k", F.floor(second(t) / seconds))
    right = b.withColumnRenamed(t, "_t").withColumn("_k", F.explode(F.array(*[F.floor(second("_t") / seconds) + d for d in (-1, 0, 1)])))
    return left.join(right, [by, "_k"]).where(F.abs(second(t) - second("_t")) <= seconds).drop("_k").withColumnRenamed("_t", f"{t}_2")


def bfs_rings(edges: DataFrame, seeds: DataFrame, most: int) -> DataFrame:
    """i, ring of nodes within `most` steps in either direction; one join a ring."""
    both = settled(edges.select(F.col("src").alias("i"), F.col("dst").alias("j")).union(edges.select("dst", "src")).distinct())
    seen = settled(seeds.select("i", F.lit(0).alias("ring")))
    for ring in range(1, most + 1):
        front = seen.where(F.col("ring") == ring - 1).select("i")
        new = both.join(front, "i").select(F.col("j").alias("i")).distinct().join(seen, "i", "left_anti")
        new = settled(new.withColumn("ring", F.lit(ring)))
        if new.isEmpty():
            break
        seen = seen.unionAll(new)
    return seen


def components(edges: DataFrame) -> DataFrame:
    """i, root: the least node that can be reached; large-star and small-star rounds."""
    now = settled(edges.where("src <> dst").select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).distinct())
    nodes = settled(edges.select(F.col("src").alias("i")).union(edges.select("dst")).distinct())
    mark = None
    while True:
        both = now.unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        now = settled(large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u <> v").distinct())
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen == mark:
            return nodes.join(now.toDF("i", "root"), "i", "left").select("i", F.coalesce("root", "i").alias("root"))
        mark = seen


def pagerank(edges: DataFrame, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """i, rank after fixed rounds, by weight; what nodes without out-edges hold is spread over all."""
    out = edges.groupBy("src").agg(F.sum("w").alias("k"))
    step = settled(edges.join(out, "src").select("src", "dst", (F.col("w") / F.col("k")).alias("p")))
    nodes = settled(edges.select(F.col("src").alias("i")).union(edges.select("dst")).distinct())
    n = nodes.count()
    rank = nodes.withColumn("rank", F.lit(1.0 / n))
    for _ in range(rounds):
        sent = rank.join(step, rank["i"] == step["src"]).groupBy("dst").agg(F.sum(F.col("rank") * F.col("p")).alias("got"))
        held = sent.agg(F.sum("got").alias("all"))
        rank = settled(nodes.join(sent.withColumnRenamed("dst", "i"), "i", "left").join(F.broadcast(held)).select("i", ((1 - damping) / n + damping * (F.coalesce("got", F.lit(0.0)) + (1 - F.col("all")) / n)).alias("rank")))
    return rank


def pack_map(df: DataFrame, key: str, k: str, v: str) -> DataFrame:
    return df.groupBy(key).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct(k, v)))).alias("packed"))


def unpack_map(df: DataFrame, key: str, k: str, v: str) -> DataFrame:
    return df.select(key, F.explode("packed").alias(k, v))


def stage_diff(edges: DataFrame, a: int, b: int) -> DataFrame:
    """Edges of stages up to a and up to b side by side: src, dst, before, after."""
    of = lambda k, name: edges.where(F.col("stage") <= k).groupBy("src", "dst").agg(F.sum("w").alias(name))
    return of(a, "before").join(of(b, "after"), ["src", "dst"], "full")


def degree_profile(edges: DataFrame) -> DataFrame:
    """One row: approximate numbers of nodes and quantiles of out-degree; sketches of constant size."""
    out = edges.groupBy("src").agg(F.sum("w").alias("k"))
    return out.agg(F.approx_count_distinct("src").alias("nodes"), F.percentile_approx("k", F.array(F.lit(0.5), F.lit(0.9), F.lit(0.99)), 1000).alias("quantiles"))
