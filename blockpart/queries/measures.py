"""Queries of correctness and cost measures."""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import functions as F

from blockpart import perf
from blockpart.operators import metrics
from blockpart.sources import workloads as W
from blockpart.sources.tables import table

QUERIES: dict = {}
#: The worked example: truth block, output block, nodes (fixed values).
TABLE = (("A", "A", 30), ("A", "B", 2), ("B", "A", 1), ("B", "B", 20), ("B", "C", 3))
ORDERS = "cont as (select o_orderstatus as t, o_orderpriority as o, count(*) as n from orders group by all)"
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
#: For the three truth blocks: of all maps of a different output to each the one that matches most, ties to the least outputs.
ORDERS_MATCH = """triple as (select x.t as t1, x.o as o1, x.n as n1, y.t as t2, y.o as o2, y.n as n2, z.t as t3, z.o as o3, z.n as n3 from cont x join cont y on x.t = 'F' and y.t = 'O' and x.o <> y.o join cont z on z.t = 'P' and z.o not in (x.o, y.o) order by x.n + y.n + z.n desc, o1, o2, o3 limit 1),
matched as (select t, o, n::bigint as n from triple, lateral (values (t1, o1, n1), (t2, o2, n2), (t3, o3, n3)) v(t, o, n))"""


def tab(s):
    return s.createDataFrame(TABLE, "t string, o string, n bigint")


def add(name, call, sql=None):
    QUERIES[name] = call, sql


def orders_nodes(s, sf):
    """Orders as nodes: the status as truth, the priority as output."""
    rows = table(s, sf, "orders", "o_orderkey", "o_orderstatus", "o_orderpriority")
    return rows.select(F.col("o_orderkey").alias("i"), F.col("o_orderstatus").alias("t")), rows.select(F.col("o_orderkey").alias("i"), F.col("o_orderpriority").alias("b"))


def orders_cont(s, sf):
    """Their contingency; both columns stand in one table, so nothing is joined."""
    return table(s, sf, "orders", F.col("o_orderstatus").alias("t"), F.col("o_orderpriority").alias("o")).groupBy("t", "o").agg(F.count(F.lit(1)).alias("n"))


def r6(df):
    return df.select(*[F.round(c, 6).alias(c) if k == "double" else F.col(c) for c, k in df.dtypes])


PAIR = """m as (select sum(n * (n - 1) / 2.0) as c1, sum(n) as n from cont), tt as (select sum(n * (n - 1) / 2.0) as x from (select sum(n) as n from cont group by t)), oo as (select sum(n * (n - 1) / 2.0) as x from (select sum(n) as n from cont group by o)),
pc as (select c1::double as c1, (n * (n - 1) / 2.0 - tt.x - oo.x + c1)::double as c2, (tt.x - c1)::double as c3, (oo.x - c1)::double as c4, (n * (n - 1) / 2.0)::double as pairs from m, tt, oo)"""
RAND = "select round(c1 / (c1 + c4), 6) as pair_precision, round(c1 / (c1 + c3), 6) as pair_recall, round((c1 + c2) / pairs, 6) as rand, round((c1 - (c1 + c3) * (c1 + c4) / pairs) / ((2 * c1 + c3 + c4) / 2 - (c1 + c3) * (c1 + c4) / pairs), 6) as adjusted_rand from pc"
INFO = """al as (select sum(n)::double as a from cont), ht as (select -sum(n / a * log2(n / a)) as h_truth from (select sum(n) as n from cont group by t), al), ho as (select -sum(n / a * log2(n / a)) as h_output from (select sum(n) as n from cont group by o), al),
mi as (select sum(cont.n / a * log2(cont.n * a / (x.n * y.n))) as information from cont join (select t, sum(n) as n from cont group by t) x using (t) join (select o, sum(n) as n from cont group by o) y using (o), al)"""
INFO_OUT = "select round(h_truth, 6) as h_truth, round(h_output, 6) as h_output, round(information, 6) as information, round(information / h_output, 6) as info_precision, round(information / h_truth, 6) as info_recall from ht, ho, mi"

add("c1_contingency_tab", lambda s, sf: metrics.contingency(*orders_nodes(s, sf)), f"with {ORDERS} select * from cont")
add("c1_cube_tab", lambda s, sf: metrics.with_totals(orders_cont(s, sf)), f"with {ORDERS} select t, o, sum(n)::bigint as n from cont group by cube (t, o)")
add("c1_pivot_tab", lambda s, sf: orders_cont(s, sf).groupBy("t").pivot("o", list(PRIORITIES)).sum("n"), f"with {ORDERS} select t, " + ", ".join(f"sum(n) filter (where o = '{o}')::bigint as \"{o}\"" for o in PRIORITIES) + " from cont group by t")
# For three truth blocks: all maps of a different output to each.
add("c2_assignment_tab", lambda s, sf: metrics.association(orders_cont(s, sf)), f"with {ORDERS}, {ORDERS_MATCH} select t, o, n from matched")
add("c3_accuracy_tab", lambda s, sf: r6(metrics.accuracy(orders_cont(s, sf), metrics.association(orders_cont(s, sf)))), f"with {ORDERS}, {ORDERS_MATCH} select (select sum(n) from matched)::bigint as matched, (select sum(n) from cont)::bigint as total, round((select sum(n) from matched) / (select sum(n) from cont)::double, 6) as accuracy")
add("c4_precision_tab", lambda s, sf: r6(metrics.block_precision(orders_cont(s, sf), metrics.association(orders_cont(s, sf)))), f"with {ORDERS}, {ORDERS_MATCH} select c.o, c.size::bigint as size, coalesce(m.n, 0)::bigint as matched, round(coalesce(m.n, 0) / c.size::double, 6) as precision from (select o, sum(n) as size from cont group by o) c left join matched m on m.o = c.o")
add("c5_recall_tab", lambda s, sf: r6(metrics.block_recall(orders_cont(s, sf), metrics.association(orders_cont(s, sf)))), f"with {ORDERS}, {ORDERS_MATCH} select c.t, c.size::bigint as size, coalesce(m.n, 0)::bigint as matched, round(coalesce(m.n, 0) / c.size::double, 6) as recall from (select t, sum(n) as size from cont group by t) c left join matched m on m.t = c.t")
add("c6_pairs_tab", lambda s, sf: metrics.pair_counts(orders_cont(s, sf)), f"with {ORDERS}, {PAIR} select * from pc")
add("c7_c10_rand_tab", lambda s, sf: r6(metrics.pair_measures(orders_cont(s, sf))), f"with {ORDERS}, {PAIR} {RAND}")
add("c12_c15_info_tab", lambda s, sf: r6(metrics.information(orders_cont(s, sf))), f"with {ORDERS}, {INFO} {INFO_OUT}")
add("c16_diagnosis_tab", lambda s, sf: metrics.diagnosis(orders_cont(s, sf)), f"with {ORDERS}, n as (select count(distinct t) as truths, count(distinct o) as outputs from cont) select *, case when outputs > truths then 'over' when outputs < truths then 'under' else 'equal' end as diagnosis from n")


def docs_cont(s, sf):
    docs = table(s, sf, "documents", "doc_id", "lang", "source")
    return metrics.contingency(docs.select(F.col("doc_id").alias("i"), F.col("lang").alias("t")), docs.select(F.col("doc_id").alias("i"), F.col("source").alias("b")))


DOCS = "cont as (select lang as t, source as o, count(*) as n from documents group by all)"
add("c17_pairs_documents", lambda s, sf: r6(metrics.pair_measures(docs_cont(s, sf))), f"with {DOCS}, {PAIR} {RAND}")
add("c17_info_documents", lambda s, sf: r6(metrics.information(docs_cont(s, sf))), f"with {DOCS}, {INFO} {INFO_OUT}")
add("c17_report_w6", lambda s, sf: r6(metrics.report(table(s, sf, "documents", "doc_id", "lang").select(F.col("doc_id").alias("i"), F.col("lang").alias("t")), table(s, sf, "documents", "doc_id", "source").select(F.col("doc_id").alias("i"), F.col("source").alias("b")))))
LABELS = "cont as (select quality as t, lang as o, count(*) as n from labels join documents using (doc_id) group by all)"
add("c17_report_labels", lambda s, sf: r6(metrics.pair_measures(metrics.contingency(table(s, sf, "labels", "doc_id", "quality").select(F.col("doc_id").alias("i"), F.col("quality").alias("t")), table(s, sf, "documents", "doc_id", "lang").select(F.col("doc_id").alias("i"), F.col("lang").alias("b"))))), f"with {LABELS}, {PAIR} {RAND}")

add("q1_edges_w2", lambda s, sf: perf.edges(W.w2(s, sf)), f"select count(*) as rows, sum(w) as weight from ({W.SQL['w2']})")


def run_cost(s, sf):
    found = perf.measured(lambda: W.w1(s, sf).agg(F.sum("w")).first()[0], s)
    return s.createDataFrame([tuple(found.values())], ", ".join(f"{k} {'boolean' if isinstance(v, bool) else 'string' if isinstance(v, str) else 'bigint' if isinstance(v, int) else 'double'}" for k, v in found.items()))


add("q2_q7_run", run_cost)


def spark_counters(s, sf):
    """Q10: what Spark counted for one pass over the trade graph."""
    before = perf.counters(s)
    W.w1(s, sf).write.format("noop").mode("overwrite").save()
    after = perf.counters(s)
    return s.createDataFrame([(k, float(after[k] - before[k])) for k in after], "counter string, value double")


add("q10_counters", spark_counters)
add("q8_loc", lambda s, sf: perf.loc(s, str(Path(__file__).resolve().parents[1])))
