"""Queries of the operators around the methods: scans, joins, aggregates, windows, sets, functions, streams, user-defined functions."""

from __future__ import annotations

import sys
import time

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import phi, sql_u01, u01
from blockpart.operators import node, relops, stats
from blockpart.sources import workloads as W
from blockpart.sources.tables import EDGES, PlantedSource, edge_list, json_edges, table, write_incidence, write_partition
from blockpart.streaming import stages as ST

QUERIES: dict = {}


def add(name, call, sql=None):
    QUERIES[name] = call, sql


T = table
add("rel_scan_prune", lambda s, sf: T(s, sf, "lineitem", "l_returnflag", "l_quantity", "l_shipdate").where("l_shipdate < timestamp_ntz '1998-09-02'").groupBy("l_returnflag").agg(F.sum("l_quantity").alias("quantity"), F.count(F.lit(1)).alias("n")), "select l_returnflag, sum(l_quantity) as quantity, count(*) as n from lineitem where l_shipdate < timestamp '1998-09-02' group by 1")
add("rel_predicates", lambda s, sf: T(s, sf, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderpriority").where((F.col("o_totalprice").between(1000, 200000) & F.col("o_orderstatus").isin("F", "O")) | F.col("o_orderpriority").like("1-%")).select("o_orderkey"), "select o_orderkey from orders where o_totalprice between 1000 and 200000 and o_orderstatus in ('F', 'O') or o_orderpriority like '1-%'")
add("rel_case_phi", lambda s, sf: T(s, sf, "part", "p_partkey", "p_size").select("p_partkey", F.round(phi(F.col("p_size") - 5), 6).alias("phi")), "select p_partkey, round(case when p_size - 5 > 0 then (p_size - 5) * ln((p_size - 5)::double) else 0.0 end, 6) as phi from part")
add("rel_sample", lambda s, sf: T(s, sf, "customer", "c_custkey").where(u01(42, "batch", 0, F.col("c_custkey")) < 0.1), "select c_custkey from customer where ('0x' || substr(md5(concat_ws('|', '42', 'batch', '0', c_custkey::varchar, '0')), 1, 13))::bigint / 4503599627370496.0 < 0.1")
add("rel_semi", lambda s, sf: T(s, sf, "customer", "c_custkey").join(T(s, sf, "orders", F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi"), "select c_custkey from customer where c_custkey in (select o_custkey from orders)")
urgent = lambda s, sf: T(s, sf, "orders", F.col("o_custkey").alias("c_custkey"), "o_orderpriority").where("o_orderpriority = '1-URGENT'")
add("rel_anti", lambda s, sf: T(s, sf, "customer", "c_custkey").join(urgent(s, sf), "c_custkey", "left_anti"), "select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_orderpriority = '1-URGENT')")
add("rel_left_coalesce", lambda s, sf: T(s, sf, "part", "p_partkey").join(T(s, sf, "lineitem", "l_partkey", "l_quantity").groupBy("l_partkey").agg(F.sum("l_quantity").alias("q")), F.col("p_partkey") == F.col("l_partkey"), "left").select("p_partkey", F.coalesce("q", F.lit(0.0)).alias("q")), "select p_partkey, coalesce(q, 0) as q from part left join (select l_partkey, sum(l_quantity) as q from lineitem group by 1) on l_partkey = p_partkey")
add("rel_broadcast", lambda s, sf: T(s, sf, "customer", "c_custkey", "c_nationkey").join(F.broadcast(T(s, sf, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")), "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by 1")
add("rel_hints", lambda s, sf: T(s, sf, "orders", "o_orderkey", "o_custkey").hint("merge").join(T(s, sf, "lineitem", "l_orderkey", "l_quantity").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.sum("l_quantity").alias("q")), "select o_custkey, sum(l_quantity) as q from orders join lineitem on o_orderkey = l_orderkey group by 1")
add("rel_asof", lambda s, sf: relops.as_of_join(T(s, sf, "events", "event_id", "user_id", "ts"), T(s, sf, "events", "event_id", "user_id", "ts", "value", "event_type").where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value")), "user_id", "ts", "value").select("event_id", "value"), "select e.event_id, p.value from events e asof left join (select user_id, ts, max(value) as value from events where event_type = 'purchase' group by all) p on e.user_id = p.user_id and e.ts >= p.ts")
add("rel_interval", lambda s, sf: relops.interval_join(T(s, sf, "events", "event_id", "event_type", "ts"), T(s, sf, "events", F.col("event_id").alias("other"), "event_type", "ts"), "event_type", "ts", 600).where("event_id < other").select("event_id", "other"), "select a.event_id, b.event_id as other from events a join events b on a.event_type = b.event_type and a.event_id < b.event_id and abs(epoch(date_trunc('second', a.ts)) - epoch(date_trunc('second', b.ts))) <= 600")
add("rel_topk", lambda s, sf: T(s, sf, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").withColumn("k", F.row_number().over(Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey"))).where("k <= 3").select("l_suppkey", "k", "l_extendedprice"), "select l_suppkey, k, l_extendedprice from (select *, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber, l_partkey) as k from lineitem) where k <= 3")
_FLOW = lambda s, sf: T(s, sf, "customer", "c_nationkey", "c_mktsegment", "c_acctbal").join(F.broadcast(T(s, sf, "nation", "n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
for _kind in ("rollup", "cube"):
    add(f"rel_{_kind}", lambda s, sf, k=_kind: getattr(_FLOW(s, sf), k)("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("bigint").alias("g")), f"select n_regionkey, c_mktsegment, count(*) as n, grouping_id(n_regionkey, c_mktsegment)::bigint as g from customer join nation on c_nationkey = n_nationkey group by {_kind} (n_regionkey, c_mktsegment)")


def grouping_sets(s, sf):
    _FLOW(s, sf).createOrReplaceTempView("flow_of_customers")
    return s.sql("select n_regionkey, c_mktsegment, count(*) as n from flow_of_customers group by grouping sets ((n_regionkey), (c_mktsegment), ())")


add("rel_grouping_sets", grouping_sets, "select n_regionkey, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey group by grouping sets ((n_regionkey), (c_mktsegment), ())")
_YEAR = lambda s, sf, y: T(s, sf, "orders", "o_custkey", "o_orderdate").where(F.year("o_orderdate") == y).select("o_custkey")
for _op, _call in (("union", lambda a, b: a.union(b).distinct()), ("union all", lambda a, b: a.unionAll(b)), ("intersect", lambda a, b: a.intersect(b)), ("except", lambda a, b: a.subtract(b)), ("intersect all", lambda a, b: a.intersectAll(b)), ("except all", lambda a, b: a.exceptAll(b))):
    add(f"rel_set_{_op.replace(' ', '_')}", lambda s, sf, c=_call: c(_YEAR(s, sf, 1996), _YEAR(s, sf, 1997)), f"select o_custkey from orders where year(o_orderdate) = 1996 {_op} select o_custkey from orders where year(o_orderdate) = 1997")
_W = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
add("rel_window_rank", lambda s, sf: T(s, sf, "customer", "c_custkey", "c_nationkey", "c_acctbal").select("c_custkey", *[f.over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias(n) for n, f in (("rn", F.row_number()), ("rk", F.rank()), ("dr", F.dense_rank()), ("nt", F.ntile(4)))], F.round(F.percent_rank().over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")), 6).alias("pr"), F.round(F.cume_dist().over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")), 6).alias("cd")), "select c_custkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from customer window w as (partition by c_nationkey order by c_acctbal, c_custkey)")
add("rel_window_offsets", lambda s, sf: T(s, sf, "events", "event_id", "user_id", "ts", "event_type").select("event_id", F.lag("event_type").over(_W()).alias("before"), F.lead("event_type").over(_W()).alias("after"), F.first_value("event_type").over(_W()).alias("first"), F.nth_value("event_type", 2).over(_W()).alias("second")), "select event_id, lag(event_type) over w as before, lead(event_type) over w as after, first_value(event_type) over w as first, nth_value(event_type, 2) over w as second from events window w as (partition by user_id order by ts, event_id)")
add("rel_window_range", lambda s, sf: T(s, sf, "events", "event_id", "user_id", "ts").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_timestamp(F.col("ts").cast("timestamp"))).rangeBetween(-86400, 0)).alias("n")), "select event_id, count(*) over (partition by user_id order by epoch(date_trunc('second', ts))::bigint range between 86400 preceding and current row) as n from events")
add("rel_distinct_agg", lambda s, sf: T(s, sf, "lineitem", "l_suppkey", "l_partkey", "l_quantity").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.max_by("l_partkey", F.struct("l_quantity", "l_partkey")).alias("most"), F.sum(F.when(F.col("l_quantity") > 25, 1).otherwise(0)).alias("large")), "select l_suppkey, count(distinct l_partkey) as parts, arg_max(l_partkey, (l_quantity, l_partkey)) as most, count(*) filter (where l_quantity > 25) as large from lineitem group by 1")
add("rel_collect", lambda s, sf: T(s, sf, "orders", "o_custkey", "o_orderkey").groupBy("o_custkey").agg(F.concat_ws(",", F.transform(F.sort_array(F.collect_list("o_orderkey")), lambda x: x.cast("string"))).alias("orders")), "select o_custkey, string_agg(o_orderkey::varchar, ',' order by o_orderkey) as orders from orders group by 1")
add("rel_statistics", lambda s, sf: T(s, sf, "lineitem", "l_quantity", "l_extendedprice").agg(F.round(F.percentile("l_quantity", 0.5), 6).alias("median"), F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope")), "select round(quantile_cont(l_quantity, 0.5), 6) as median, round(stddev(l_quantity), 6) as sd, round(corr(l_quantity, l_extendedprice), 6) as corr, round(regr_slope(l_extendedprice, l_quantity), 3) as slope from lineitem")
add("rel_sketches", lambda s, sf: relops.degree_profile(W.w2(s, sf)))
add("rel_string_links", lambda s, sf: T(s, sf, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), F.length("url").cast("bigint").alias("n"), F.upper(F.substring("url", 1, 4)).alias("head")), "select page_id, regexp_extract(url, '^https?://([^/]+)', 1) as host, length(url) as n, upper(substr(url, 1, 4)) as head from pages")
add("rel_string_distance", lambda s, sf: T(s, sf, "nation", "n_nationkey", "n_name").select("n_nationkey", F.levenshtein("n_name", F.lit("NATION")).cast("bigint").alias("d"), F.md5("n_name").alias("h")), "select n_nationkey, levenshtein(n_name, 'NATION') as d, md5(n_name) as h from nation")
add("rel_date", lambda s, sf: T(s, sf, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("bigint").alias("d")), "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, date_diff('day', timestamp '1995-01-01', o_orderdate) as d from orders")
add("rel_json", lambda s, sf: T(s, sf, "events", "event_id", "props").select("event_id", F.from_json("props", "k bigint").k.alias("k")), "select event_id, (props->>'k')::bigint as k from events")
add("rel_json_variant", lambda s, sf: T(s, sf, "events", "event_id", "props").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k")), "select event_id, (props->>'k')::bigint as k from events")
add("rel_array_norm", lambda s, sf: T(s, sf, "embeddings", "vec_id", "embedding").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x), 5).alias("norm")), "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x)), 5) as norm from embeddings")
add("rel_map_pack", lambda s, sf: relops.unpack_map(relops.pack_map(node.node_block(W.w1(s, sf), W.region_of_nation(s, sf)), "i", "t", "k_out"), "i", "t", "k_out"), f"with e as ({W.SQL['w1']}) select src as i, n_regionkey::bigint as t, sum(w) as k_out from (select src, dst, w from e where src <> dst union all select dst, src, 0 from e where src <> dst) join nation on n_nationkey = dst group by all")
add("rel_recursive", lambda s, sf: s.sql("with recursive t(k, x) as (select 0, 1 union all select k + 1, x * 2 from t where k < 10) select k, x from t"), "with recursive t(k, x) as (select 0, 1 union all select k + 1, x * 2 from t where k < 10) select k, x from t")
add("rel_full_outer", lambda s, sf: _YEAR(s, sf, 1996).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("a")).join(_YEAR(s, sf, 1997).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("b")), "o_custkey", "full"), "select coalesce(x.o_custkey, y.o_custkey) as o_custkey, a, b from (select o_custkey, count(*) as a from orders where year(o_orderdate) = 1996 group by 1) x full join (select o_custkey, count(*) as b from orders where year(o_orderdate) = 1997 group by 1) y on x.o_custkey = y.o_custkey")


def sql_udf(s, sf):
    s.sql("create or replace temporary function phi_of(x double) returns double return case when x > 0 then x * ln(x) else 0.0D end")
    T(s, sf, "part", "p_partkey", "p_retailprice").createOrReplaceTempView("part_prices")
    return s.sql("select p_partkey, round(phi_of(p_retailprice), 4) as v from part_prices")


add("udf_phi_sql", sql_udf, "select p_partkey, round(case when p_retailprice > 0 then p_retailprice * ln(p_retailprice) else 0.0 end, 4) as v from part")


def udaf(s, sf):
    @F.pandas_udf("double")
    def objective(m: pd.Series) -> float:
        import numpy as np

        return float((m * np.log(m)).sum())

    return stats.cells(W.w1(s, sf), W.region_of_nation(s, sf)).groupBy("r").agg(F.round(objective("m"), 4).alias("v"))


add("udaf_logpost", udaf, f"with e as ({W.SQL['w1']}), c as (select a.n_regionkey::bigint as r, b.n_regionkey as s, sum(w) as m from e join nation a on a.n_nationkey = src join nation b on b.n_nationkey = dst group by all) select r, round(sum(m * ln(m)), 4) as v from c group by r")


def udtf(s, sf):
    @F.udtf(returnType="src bigint, dst bigint, w double")
    class Adjacency:
        def eval(self, line: str):
            head, *rest = line.split()
            for x in rest:
                yield int(head), int(x), 1.0

    s.udtf.register("adjacency", Adjacency)
    return s.sql("select a.* from values ('1 2 3'), ('2 3') t(line), lateral adjacency(line) a")


add("udtf_adjacency", udtf, "select * from (values (1::bigint, 2::bigint, 1.0::double), (1, 3, 1.0), (2, 3, 1.0)) t(src, dst, w)")


def poisson_udf(s, sf):
    @F.pandas_udf("bigint")
    def quantile(x: pd.Series, rate: pd.Series) -> pd.Series:
        """Inverse Poisson by a running product; large rates by the normal tail's start."""
        import numpy as np

        out = []
        for u, r in zip(x, rate, strict=True):
            k, term = 0, np.exp(-r)
            total = term
            while total <= u and k < r + 40 * (1 + np.sqrt(r)):
                k += 1
                term *= r / k
                total += term
            out.append(k)
        return pd.Series(out)

    rows = T(s, sf, "customer", "c_custkey").select("c_custkey", u01(42, "pois", 0, F.col("c_custkey")).alias("x"))
    return rows.select("c_custkey", quantile("x", F.lit(50.0)).alias("n"))


_QUANTILE = """with cdf as materialized (select k, sum(exp(k * ln(50.0) - 50 - lgamma(k + 1))) over (order by k) as c from range(300) t(k))
select c_custkey, (select count(*) from cdf where c <= x) as n from (select c_custkey, """ + sql_u01(42, "pois", 0, "c_custkey") + """ as x from customer)"""
add("udf_pandas_poisson", poisson_udf, _QUANTILE)


# Sources and sinks
def planted_source(s, sf):
    # Planning workers need not have this library on their path.
    cloudpickle.register_pickle_by_value(sys.modules[PlantedSource.__module__])
    s.dataSource.register(PlantedSource)
    return s.read.format("planted").option("nodes", 200).option("blocks", 4).load()


add("src_planted", planted_source)


def text_round_trip(kind):
    def call(s, sf):
        path = relops.scratch_path(s, "edges")
        edges = W.w1(s, sf)
        if kind == "csv":
            edges.write.option("sep", "\t").csv(path)
            return edge_list(s, path)
        if kind == "json":
            edges.write.json(path)
            return json_edges(s, path)
        return write_incidence(edges, "incidence_w1", 4).groupBy("i").agg(F.sum("w_out").alias("o"), F.sum("w_in").alias("n"))

    return call


add("src_edge_list", text_round_trip("csv"), W.SQL["w1"])
add("src_json", text_round_trip("json"), W.SQL["w1"])
add("sink_bucketed", text_round_trip("bucket"), f"with e as ({W.SQL['w1']}) select i, sum(o) as o, sum(n) as n from (select src as i, w as o, 0.0 as n from e where src <> dst union all select dst, 0.0, w from e where src <> dst) group by i")


# Streams, each read as files and finished at once; SQL judges the batch twin.
def streamed(kind):
    def call(s, sf):
        schema = s.read.parquet(f"{sf}/events.parquet").schema
        source = s.readStream.schema(schema).parquet(f"{sf}/events*.parquet")
        out = ST.windowed(ST.event_edges(source), kind)
        return ST.finished(out, "complete", relops.scratch_path(s, f"stream-{kind}")).withColumn("w", F.round("w", 4)).select(F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), *(["src"] if kind == "session" else []), "w", "n")

    return call


add("stream_tumbling", streamed("tumbling"), "select date_trunc('day', ts)::timestamp as start, date_trunc('day', ts)::timestamp + interval 1 day as \"end\", round(sum(value), 4) as w, count(*) as n from events group by 1, 2")
add("stream_sliding", streamed("sliding"), "select start, start + interval 2 day as \"end\", round(sum(value), 4) as w, count(*) as n from (select value, unnest([date_trunc('day', ts)::timestamp, date_trunc('day', ts)::timestamp - interval 1 day]) as start from events) group by 1, 2")
add("stream_session", streamed("session"), "select min(ts) as start, max(ts) + interval 10 minute as \"end\", 4 * user_id as src, round(sum(value), 4) as w, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as k from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 10 minute then 0 else 1 end as fresh from events)) group by user_id, k")
add("r3_warm_majority_w4", lambda s, sf: ST.warm_start(W.w4(s, sf), W.each_alone(W.w4(s, sf)).where("i % 7 <> 0").select("i", (F.col("i") % 5).alias("b"))), f"""with e as materialized ({W.SQL['w4']}), nodes as (select src as i from e union select dst from e), old as (select i, i % 5 as b from nodes where i % 7 <> 0),
near as (select x.i, o.b as t, sum(w) as k from (select src as i, dst as j, w from e where src <> dst union all select dst, src, w from e where src <> dst) x join old o on o.i = x.j group by all),
best as (select i, t from (select *, row_number() over (partition by i order by k desc, t) as r from near) where r = 1)
select n.i, coalesce(o.b, best.t, -1 - n.i) as b from nodes n left join old o on o.i = n.i left join best on best.i = n.i""")
add("r6_increment_cells_w4", lambda s, sf: _increment(s, sf), f"select a % 5 as r, b % 5 as s, sum(w) as m from (select src as a, dst as b, w from ({W.SQL['w4']})) group by all")


def _increment(s, sf):
    from blockpart.operators import stages

    staged = stages.emerging(W.w4(s, sf), 10)
    assign = W.each_alone(W.w4(s, sf)).select("i", (F.col("i") % 5).alias("b"))
    return stats.add_edges(stats.cells(stages.upto(staged, 6), assign), staged.where("stage > 6"), assign)


def planted_stages(s, sf, kind="emerging"):
    """A planted graph on the vectors' ids, in four stages: edges at random, or a snowball from the first node."""
    from blockpart.operators import generate, stages

    nodes = T(s, sf, "embeddings", "vec_id").select(F.col("vec_id").cast("bigint").alias("i"))
    edges, truth = generate.preset(nodes, "base", 5)
    edges = relops.settled(edges)
    staged = stages.emerging(edges, 4) if kind == "emerging" else stages.snowball(edges, nodes.agg(F.min("i").alias("i")), 4)
    return relops.settled(staged), relops.settled(truth)


def staged_run(kind, **options):
    def call(s, sf):
        rows = ST.run(*planted_stages(s, sf, kind), **options)
        names = ("accuracy", "pair_precision", "pair_recall", "rand", "adjusted_rand", "info_precision", "info_recall")
        out = [(r["stage"], r["n"], float(r["e"]), r["blocks"], round(r["h_val"], 6), r["tries"], r["warm"], *(None if r[k] is None else round(r[k], 6) for k in names), r["diagnosis"], r["sec"], r["rate"]) for r in rows]
        kinds = "stage bigint, n bigint, e double, blocks bigint, h_val double, tries bigint, warm boolean, " + ", ".join(f"{k} double" for k in names) + ", diagnosis string, sec double, rate double"
        return s.createDataFrame(out, kinds)

    return call


add("r1_stages_w11_cold", staged_run("emerging", warm="none"))
add("r3_stages_w11_warm", staged_run("emerging"))
add("r3b_stages_w11_majority", staged_run("emerging", new="majority"))
add("r4_stages_w11_reuse", staged_run("emerging", bracket="reuse"))
add("r1_stages_w12_cold", staged_run("snowball", warm="none"))
add("r3_stages_w12_warm", staged_run("snowball"))


def stream_partition(s, sf):
    path = relops.scratch_path(s, "stream")
    from blockpart.operators import stages

    staged = relops.settled(stages.emerging(W.w1(s, sf), 2))
    for k in (1, 2):
        stages.only(staged, k).select("src", "dst", "w").coalesce(1).write.mode("append").parquet(f"{path}/e")
    source = s.readStream.schema(EDGES).option("maxFilesPerTrigger", 1).parquet(f"{path}/e")
    rows = ST.partition_stream(source, f"{path}/check")
    return s.createDataFrame([tuple(r.values()) for r in rows], "batch bigint, e double, blocks bigint, h_val double")


add("stream_partition", stream_partition)


def stream_once(s, sf):
    """Every event delivered twice, one delivery a batch; the stream keeps one of each."""
    path = relops.scratch_path(s, "twice")
    events = T(s, sf, "events")
    events.write.parquet(path)
    files = len(s.read.schema(events.schema).parquet(path).inputFiles())  # of one delivery; a stream takes the older files first
    events.write.mode("append").parquet(path)
    source = ST.event_edges(s.readStream.schema(events.schema).option("maxFilesPerTrigger", files).parquet(path))
    out = ST.deduplicated(source, watermark="3650 days").select("event_id", "src", "dst")
    return ST.finished(out, "append", relops.scratch_path(s, "once"))


add("stream_dedupe", stream_once, "select event_id, 4 * user_id as src, ('0x' || substr(md5(event_type), 1, 13))::bigint * 4 + 1 as dst from events")


def stream_static(s, sf):
    """A stream of events joined with the table of customers."""
    source = s.readStream.schema(T(s, sf, "events").schema).parquet(f"{sf}/events*.parquet")
    known = T(s, sf, "customer", "c_custkey", "c_nationkey")
    out = source.join(known, F.col("user_id") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))
    return ST.finished(out, "complete", relops.scratch_path(s, "stream-static"))


add("stream_static_join", stream_static, "select c_nationkey, count(*) as n from events join customer on user_id = c_custkey group by 1")


def stream_stream(s, sf):
    """Two streams of events, joined on the user within ten minutes after a click of another kind."""
    schema = T(s, sf, "events").schema
    side = lambda name: s.readStream.schema(schema).parquet(f"{sf}/events*.parquet").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", "1 hour").alias(name)
    near = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_type") < F.col("b.event_type")) & (F.col("b.ts") >= F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("interval 10 minutes"))
    out = side("a").join(side("b"), near).select(F.col("a.event_id").alias("one"), F.col("b.event_id").alias("two"))
    return ST.finished(out, "append", relops.scratch_path(s, "stream-stream"))


add("stream_stream_join", stream_stream, "select a.event_id as one, b.event_id as two from events a join events b on a.user_id = b.user_id and a.event_type < b.event_type and b.ts >= a.ts and b.ts <= a.ts + interval 10 minute")


def rate_source(s, sf):
    """Rows of the built-in source, a fixed number a batch."""
    source = s.readStream.format("rate-micro-batch").option("rowsPerBatch", 50).load()
    path = relops.scratch_path(s, "rate")
    done = source.select("value").writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-check").trigger(processingTime="0 seconds").start()
    try:
        while done.lastProgress is None or done.lastProgress["batchId"] < 1:
            time.sleep(0.1)
    finally:
        done.stop()
    return s.read.parquet(path).where("value < 50").select((F.col("value") % 5).alias("src"), (F.col("value") % 7).alias("dst"))


add("src_rate", rate_source, "select v % 5 as src, v % 7 as dst from range(50) t(v)")


def kept_partitions(s, sf):
    """Partitions of the history, each under its number of blocks, and a view over one of them."""
    path = relops.scratch_path(s, "history")
    for blocks in (5, 3):
        write_partition(W.each_alone(W.w1(s, sf)).select("i", (F.col("i") % blocks).alias("b")), blocks, path)
    s.read.parquet(path).createOrReplaceTempView("kept_partitions")
    return s.sql("select blocks, b, count(*) as n from kept_partitions where blocks = 3 group by all")


add("sink_partitions", kept_partitions, f"with e as ({W.SQL['w1']}) select 3 as blocks, i % 3 as b, count(*) as n from (select src as i from e union select dst from e) group by all")


def view_of_method(s, sf):
    """SQL over what a method gives: block sizes of a partition, through a view."""
    W.region_of_nation(s, sf).createOrReplaceTempView("partition_by_region")
    return s.sql("select b, count(*) as n, min(i) as least from partition_by_region group by b having count(*) > 1")


add("rel_view_of_method", view_of_method, "select n_regionkey::bigint as b, count(*) as n, min(n_nationkey)::bigint as least from nation group by 1 having count(*) > 1")


def grouped_map(s, sf):
    """Per user, the longest gap between events: a function over each group's frame."""

    def gap(pdf: pd.DataFrame) -> pd.DataFrame:
        ts = pdf["ts"].sort_values()
        return pd.DataFrame({"user_id": [pdf["user_id"].iloc[0]], "gap": [int(ts.diff().max().total_seconds() // 1) if len(ts) > 1 else 0]})

    return T(s, sf, "events", "user_id", "ts").groupBy("user_id").applyInPandas(gap, "user_id bigint, gap bigint")


add("udf_grouped_map", grouped_map, "select user_id, coalesce(floor(max(epoch_us(ts) - epoch_us(p)) / 1000000), 0)::bigint as gap from (select user_id, ts, lag(ts) over (partition by user_id order by ts) as p from events) group by 1")
