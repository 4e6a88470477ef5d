"""Cost measures: edges, time, rate, energy, memory, processors, lines of code, growth."""

from __future__ import annotations

import os
import threading
import time
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Watts of a busy core where the machine tells no energy; results are then flagged as estimated.
WATTS_PER_CORE = 8.0


def edges(graph: DataFrame) -> DataFrame:
    return graph.agg(F.count(F.lit(1)).alias("rows"), F.sum("w").alias("weight"))


def _joules() -> float | None:
    try:
        return sum(int(p.read_text()) for p in Path("/sys/class/powercap").glob("intel-rapl:?/energy_uj")) / 1e6 or None
    except OSError:
        return None


def _tree() -> tuple[float, float]:
    """CPU seconds and resident MB of this process and all below it: the driver, the JVM, and in local mode the workers."""
    tick, page, parent, own = os.sysconf("SC_CLK_TCK"), os.sysconf("SC_PAGE_SIZE"), {}, {}
    for p in Path("/proc").glob("[0-9]*/stat"):
        try:
            f = p.read_text().rsplit(")", 1)[1].split()
        except OSError:  # it ended meanwhile
            continue
        parent[int(p.parent.name)] = int(f[1])
        own[int(p.parent.name)] = sum(map(int, f[11:15])) / tick, int(f[21]) * page / 2**20
    inside = lambda k: k == os.getpid() or (parent.get(k, 0) > 1 and inside(parent[k]))
    mine = [own[k] for k in own if inside(k)]
    return sum(x for x, _ in mine), sum(x for _, x in mine)


def counters(spark: SparkSession) -> dict[str, float]:
    """What Spark counts over all executors so far: tasks, seconds of tasks and of garbage collection, bytes read and shuffled."""
    gateway = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    out = {"tasks": 0.0, "task_sec": 0.0, "gc_sec": 0.0, "input_mb": 0.0, "shuffle_read_mb": 0.0, "shuffle_write_mb": 0.0}
    for k in range(gateway.size()):
        x = gateway.apply(k)
        for name, value in zip(out, (x.totalTasks(), x.totalDuration() / 1e3, x.totalGCTime() / 1e3, x.totalInputBytes() / 2**20, x.totalShuffleRead() / 2**20, x.totalShuffleWrite() / 2**20), strict=True):
            out[name] += value
    return out


def measured(run: Callable[[], float], spark: SparkSession | None = None) -> dict:
    """Runs something that returns a number of edges: seconds, rate, joules and mean watts, rate per watt, peak memory, processors; with a session also Spark's counters.

    Processor time is that of the driver, its JVM and local workers; executors elsewhere add the time of their tasks. Without a meter joules are estimated from it.
    """
    before = counters(spark) if spark else {}
    wall, cpu, energy, peak, done = time.monotonic(), _tree()[0], _joules(), [_tree()[1]], threading.Event()

    def watch() -> None:
        while not done.wait(0.2):
            peak.append(_tree()[1])

    watcher = threading.Thread(target=watch, daemon=True)
    watcher.start()
    try:
        e = run()
    finally:
        done.set()
        watcher.join()
    seconds, busy, now = time.monotonic() - wall, _tree()[0] - cpu, _joules()
    more = {k: v - before[k] for k, v in counters(spark).items()} if spark else {}
    if spark and not spark.sparkContext.master.startswith("local["):
        busy += more["task_sec"]
    joules = now - energy if now and energy else busy * WATTS_PER_CORE
    cpuinfo = Path("/proc/cpuinfo")
    model = next((x.split(":")[1].strip() for x in cpuinfo.read_text().splitlines() if x.startswith("model name")), "") if cpuinfo.exists() else ""
    watts = joules / seconds if seconds else 0.0
    own = {"edges": e, "sec": seconds, "rate": e / seconds, "cpu_sec": busy, "joules": joules, "watts": watts, "estimated": now is None, "rate_per_watt": e / seconds / watts if watts else 0.0, "peak_mb": max(peak), "processors": os.cpu_count(), "processor": model}
    return own | more


def loc(spark: SparkSession, path: str) -> DataFrame:
    """Code lines without blanks and comments, per file."""
    rows = spark.read.text(f"{path}/**/*.py", recursiveFileLookup=False).select(F.input_file_name().alias("file"), F.trim("value").alias("line"))
    return rows.where("line <> '' and not line like '#%'").groupBy(F.regexp_extract("file", r"([^/]+)$", 1).alias("file")).agg(F.count(F.lit(1)).alias("lines"))


def scaling_fit(runs: DataFrame) -> DataFrame:
    """runs(e, sec) to the slope of ln rate against ln e, and what E log^2 E gives over the same points."""
    law = 1.0 / F.pow(F.ln("e"), 2)
    return runs.agg(F.regr_slope(F.ln(F.col("e") / F.col("sec")), F.ln("e")).alias("slope"), F.regr_slope(F.ln(law), F.ln("e")).alias("law_slope"))
