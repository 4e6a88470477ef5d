"""Queries of the graphs, the objective, the node step, sweeps, merges, search, matrix form, generator, stages and baselines."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import functions as F

from blockpart import perf
from blockpart.functions.math import h, sql_phi, sql_u01, string_id
from blockpart.operators import baselines, generate, matrix, merge, metrics, node, relops, stages, stats
from blockpart.plans import search, sweep
from blockpart.queries import sqltext as T
from blockpart.sources import workloads as W
from blockpart.sources.tables import table

QUERIES: dict = {}
SEED = 42


def add(name, call, sql=None):
    QUERIES[name] = call, sql


def ints(n):
    return lambda s: s.range(n).toDF("i")


def assign_of(kind, s, sf, edges):
    if kind == "region":
        return W.region_of_nation(s, sf)
    if kind == "language":
        return W.language_of_document(s, sf)
    alone = W.each_alone(edges)
    return alone if kind == "alone" else alone.select("i", (F.col("i") % 5).alias("b"))


def with_model(graph, kind, then, counted=True):
    """A query over a graph, a partition and, unless it has no use for them, the counts, each written once."""

    def call(s, sf):
        edges = relops.settled(W.GRAPHS[graph](s, sf))
        assign = relops.settled(assign_of(kind, s, sf, edges))
        return then(edges, assign, relops.settled(stats.cells(edges, assign)) if counted else None)

    return call


def rounded(df, *columns):
    return df.withColumns({c: F.round(c, 6) for c in columns})


# Graphs
NAMES = {"w1": "trade", "w2": "custsupp", "w3": "copurchase", "w4": "transitions", "w5": "knn", "w6": "doc_token", "w6b": "doc_token_bipartite", "w7": "page_links", "w8": "role"}
for _g in W.GRAPHS:
    _name = {"w6": "w6_doc_token_pairs", "w6b": "w6b_doc_token_bipartite", "w7": "w7_page_links"}.get(_g, f"{_g}_{NAMES[_g]}" + ("" if _g == "w4" else "_edges"))
    add(_name, W.GRAPHS[_g], W.SQL[_g])
add("g10_symmetrise_w4", lambda s, sf: generate.symmetrise(W.w4(s, sf)), f"select least(src, dst) as src, greatest(src, dst) as dst, sum(w) as w from ({W.SQL['w4']}) group by all")
add("g10_binarise_w1", lambda s, sf: generate.binarise(W.w1(s, sf)), f"select distinct src, dst, 1.0::double as w from ({W.SQL['w1']})")
_DEG = "select i, sum(o) as k_out, sum(n) as k_in, count(distinct j) as neighbours from (select src as i, dst as j, w as o, 0.0 as n from e union all select dst, src, 0.0, w from e) group by i"
add("graph_degrees_w2", lambda s, sf: generate.degrees(W.w2(s, sf)), f"with e as ({W.SQL['w2']}) {_DEG}")
add("graph_isolated_w6", lambda s, sf: table(s, sf, "documents", "doc_id").join(W.each_alone(W.w6(s, sf)).select(F.col("i").alias("doc_id")), "doc_id", "left_anti"), f"with e as ({W.SQL['w6']}) select doc_id from documents where doc_id not in (select src from e union select dst from e)")
add("graph_validate_w1", lambda s, sf: W.w1(s, sf).agg(F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("nulls"), F.count_if(F.col("w") <= 0).alias("not_positive"), (F.count(F.lit(1)) - F.count_distinct("src", "dst")).alias("repeated")), f"select count_if(src is null or dst is null)::bigint as nulls, count_if(w <= 0)::bigint as not_positive, count(*) - count(distinct (src, dst)) as repeated from ({W.SQL['w1']})")
add("graph_degree_hist_w2", lambda s, sf: generate.degrees(W.w2(s, sf)).groupBy(F.floor(F.log2(F.col("k_out") + F.col("k_in"))).alias("bin")).agg(F.count(F.lit(1)).alias("nodes")), f"with e as ({W.SQL['w2']}) select floor(log2(k_out + k_in))::bigint as bin, count(*) as nodes from ({_DEG}) group by 1")

# Objective
for _g, _k in (("w1", "region"), ("w4", "mod5"), ("w6", "language")):
    add(f"o1_cells_{_g}", with_model(_g, _k, lambda e, a, c: c), f"{T.model(_g, _k)} select r, s, m from cells")
    add(f"o2_bdeg_{_g}", with_model(_g, _k, lambda e, a, c: stats.block_degrees(c)), f"{T.model(_g, _k)} select t, d_out, d_in, d from bdeg")
    add(f"o5_dl_{_g}", with_model(_g, _k, lambda e, a, c: rounded(stats.description_length(c, a), "s_val", "model", "labels", "data", "h_val")), f"{T.model(_g, _k)} {T.dl()}")
for _g, _k in (("w1", "region"), ("w1", "alone"), ("w2", "alone"), ("w4", "alone"), ("w8", "alone"), ("w6", "language")):
    add(f"o3_logpost_{_g}_{_k}", with_model(_g, _k, lambda e, a, c: rounded(stats.log_posterior(c), "s_val")), f"{T.model(_g, _k)} select round({T.S_VAL}, 6) as s_val")
add("o6_dl_terms_w8", with_model("w8", "alone", lambda e, a, c: rounded(stats.description_length(c, a), "s_val", "model", "labels", "data", "h_val")), f"{T.model('w8', 'alone')} {T.dl()}")
for _g, _k in (("w6", "language"), ("w3", "mod5")):
    add(f"o7_undirected_{_g}", with_model(_g, _k, lambda e, a, c: rounded(stats.description_length(stats.undirected_counts(e, a), a, directed=False), "s_val", "model", "labels", "data", "h_val")), f"{T.undirected(_g, _k)} {T.dl(False)}")
add("o8_binary_w1", lambda s, sf: rounded(stats.log_posterior(stats.cells(generate.binarise(W.w1(s, sf)), W.region_of_nation(s, sf))), "s_val"), f"{T.model('w1', 'region').replace('sum(w)', 'count(*)::double')} select round({T.S_VAL}, 6) as s_val")
add("o9_plain_w1", with_model("w1", "region", lambda e, a, c: rounded(stats.log_posterior_plain(c, a), "s_val")), f"{T.model('w1', 'region')} select round(sum(m * ln(m / (x.n * y.n))), 6) as s_val from cells join (select b, count(*)::double as n from assign group by b) x on x.b = r join (select b, count(*)::double as n from assign group by b) y on y.b = s")
add("o4_h_function", lambda s, sf: s.range(20).select("id", F.round(h(F.col("id") / 4), 9).alias("h")), f"select id, round({T.H_OF('(id / 4.0)')}, 9) as h from range(20) t(id)")

# Node step
for _g, _k in (("w1", "region"), ("w4", "mod5")):
    def _parts(e, a, c, _eps=None):
        near, selfs = relops.settled(node.node_block(e, a)), node.self_weights(e)
        weights = relops.settled(node.node_weights(near, selfs, a))
        deg = relops.settled(stats.block_degrees(c))
        props = relops.settled(node.propose(weights, a, c, deg, 5, SEED, 0, _eps))
        change = relops.settled(node.cell_delta(props, near, selfs))
        return near, selfs, weights, deg, props, change

    def _gain(e, a, c):
        near, selfs, _, deg, props, change = _parts(e, a, c)
        return node.delta_s(props, change, c, deg, near, selfs)

    def _hast(e, a, c):
        near, selfs, weights, deg, props, change = _parts(e, a, c)
        return node.hastings(relops.settled(node.delta_s(props, change, c, deg, near, selfs)), change, c, deg, weights, selfs, 5)

    _m, _n = T.model(_g, _k), T.near()
    add(f"n1_nodeblock_{_g}", with_model(_g, _k, lambda e, a, c: node.node_block(e, a), False), f"{_m}, {_n} select i, t, k_out, k_in from near")
    add(f"n2_neighbour_block_{_g}", with_model(_g, _k, lambda e, a, c: node.neighbour_block(node.node_weights(node.node_block(e, a), node.self_weights(e), a), SEED, 0), False), f"{_m}, {_n}, {T.pick(SEED, 0)} select i, u from picked")
    add(f"n3_propose_{_g}", with_model(_g, _k, lambda e, a, c: _parts(e, a, c)[4]), f"{_m}, {_n}, {T.propose(SEED, 0, 5)} select i, r, u, s, kind from props")
    add(f"n3_fixed_eps_{_g}", with_model(_g, _k, lambda e, a, c: _parts(e, a, c, 0.3)[4]), f"{_m}, {_n}, {T.propose(SEED, 0, 5, 0.3)} select i, r, u, s, kind from props")
    add(f"n5_celldelta_{_g}", with_model(_g, _k, lambda e, a, c: _parts(e, a, c)[5]), f"{_m}, {_n}, {T.propose(SEED, 0, 5)}, {T.CHANGE} select i, p, q, dm from chg")
    add(f"n6_deltas_{_g}", with_model(_g, _k, lambda e, a, c: rounded(_gain(e, a, c), "d_s")), f"{_m}, {_n}, {T.propose(SEED, 0, 5)}, {T.CHANGE}, {T.GAIN} select i, r, s, k_out, k_in, round(d_s, 6) as d_s from gain")
    add(f"n7_hastings_{_g}", with_model(_g, _k, lambda e, a, c: rounded(_hast(e, a, c), "p_fwd", "p_bwd")), f"{_m}, {_n}, {T.propose(SEED, 0, 5)}, {T.CHANGE}, {T.GAIN}, {T.hastings(5)} select i, round(p_fwd, 6) as p_fwd, round(p_bwd, 6) as p_bwd from chance")
    add(f"n8_accept_{_g}", with_model(_g, _k, lambda e, a, c: node.evaluate(e, a, c, 5, SEED, 0).select("i", "r", "s", F.round("a", 6).alias("a"), "accept")), f"{T.step(_g, _k, SEED, 0, 5)} select i, r, s, round(a, 6) as a, draw < a as accept from decided")
    add(f"v2_sweep1_{_g}", with_model(_g, _k, lambda e, a, c: sweep.synchronous(e, a, 5, SEED, 0, counts=c)), f"{T.step(_g, _k, SEED, 0, 5)} select a.i, coalesce(d.s, a.b) as b from assign a left join (select * from decided where draw < a) d on d.i = a.i")
    add(f"v5_refresh_{_g}", with_model(_g, _k, lambda e, a, c: node.refresh_cells(c, e, a, sweep.synchronous(e, a, 5, SEED, 0, counts=c))), f"{T.step(_g, _k, SEED, 0, 5)}, after as (select a.i, coalesce(d.s, a.b) as b from assign a left join (select * from decided where draw < a) d on d.i = a.i) select x.b as r, y.b as s, sum(w) as m from edges join after x on x.i = src join after y on y.i = dst group by all")
    add(f"v6_influence_{_g}", with_model(_g, _k, lambda e, a, c: rounded(node.influence(e, node.evaluate(e, a, c, 5, SEED, 0).where("accept").select("i")), "mean_neighbours")), f"{T.step(_g, _k, SEED, 0, 5)}, pairs as (select distinct least(src, dst) as x, greatest(src, dst) as y from edges where src <> dst), mv as (select i from decided where draw < a) select (select count(*) from pairs) as pairs, (select count(*) from pairs where x in (select i from mv) and y in (select i from mv)) as together, round((select 2.0 * count(*) from pairs) / (select count(*) from (select x from pairs union select y from pairs)), 6) as mean_neighbours")
add("v2_damped_w4", with_model("w4", "mod5", lambda e, a, c: sweep.synchronous(e, a, 5, SEED, 0, damp=0.5, counts=c)), f"{T.step('w4', 'mod5', SEED, 0, 5)} select a.i, coalesce(d.s, a.b) as b from assign a left join (select * from decided where draw < a and {sql_u01(SEED, 'batch', 0, 'i')} < 0.5) d on d.i = a.i")


def _batch_sql(k, before):
    """Blocks after the k-th of two batches of w4, from the query `before` of the blocks so far."""
    step = T.step("w4", before, SEED, 0, 5)
    return f"{step} select a.i, coalesce(d.s, a.b) as b from assign a left join (select * from decided where draw < a and floor({sql_u01(SEED, 'batch', 0, 'i')} * 2) = {k}) d on d.i = a.i"


add("v3_batched_w4", with_model("w4", "mod5", lambda e, a, c: sweep.batched(e, a, 5, SEED, 0, 2), False), _batch_sql(1, _batch_sql(0, "mod5")))
add("v4_local_w4", with_model("w4", "mod5", lambda e, a, c: sweep.partition_local(e, a, 5, SEED, 0), False))
add("v1_sequential_w1", with_model("w1", "region", lambda e, a, c: sweep.sequential(e, a, 5, SEED, 0), False))


def stop_rule(s, sf):
    """After which sweeps of a series the rule stops."""
    series = [-100.0 / (k + 1) for k in range(30)]
    return s.createDataFrame([(k, bool(sweep.converged(series[: k + 1], 0.05))) for k in range(30)], "id bigint, stop boolean")


add("n11_stop_rule", stop_rule, "select id, coalesce((s - lag(s, 3) over (order by id)) / 3 < 0.05 * abs(s), false) as stop from (select id, -100.0::double / (id + 1) as s from range(30) t(id))")

# Merges
_PAIRS = "props as materialized (select distinct hash(r, s) as i, r, s from (select r, s from cells where r <> s union select s, r from cells where r <> s))"
_BLOCK = f"""blk as (select * from cells), near as (select p.i, x.t, sum(o) as k_out, sum(n) as k_in from props p join (select r as b, s as t, m as o, 0.0 as n from blk where r <> s union all select s, r, 0.0, m from blk where r <> s) x on x.b = p.r group by all),
selfs as (select p.i, m as w_self from props p join blk on blk.r = p.r and blk.s = p.r)"""
_SCORED = f"{T.model('w1', 'region')}, {_PAIRS}, {_BLOCK}, {T.CHANGE}, {T.GAIN}"
add("b6_pairs_w1", with_model("w1", "region", lambda e, a, c: rounded(merge.score(merge.all_pairs(c), c), "d_s")), f"{_SCORED} select r, s, round(d_s, 6) as d_s from gain")
add("b4_best_w1", with_model("w1", "region", lambda e, a, c: rounded(merge.best_per_block(merge.score(merge.all_pairs(c), c)), "d_s")), f"{_SCORED} select r, s, round(d_s, 6) as d_s from (select *, row_number() over (partition by r order by round(d_s, 9) desc, s) as k from gain) where k = 1")
_OUTER = "outer_ as materialized (select u, t, sum(m) over (partition by u order by t rows unbounded preceding) as high, m, sum(m) over (partition by u) as total from sym where u <> t)"


def _merge_draws(blocks, tries, seed):
    """props(r, s): the draws of merges by SQL."""
    u = lambda k: sql_u01(seed, "prop", 0, "i", k)
    return f"""keyed as materialized (select t as r, k, t || ':' || k as i from bdeg, range({tries}) x(k)),
near_ as materialized (select k.i, k.r, o.t as u from keyed k left join outer_ o on o.u = k.r and o.high - o.m <= {u(0).replace("(i)", "(k.i)")} * o.total and {u(0).replace("(i)", "(k.i)")} * o.total < o.high),
drawn as materialized (select n.i, n.r, n.u, n.u is null or {u(1).replace("(i)", "(n.i)")} < {float(blocks)} / (d + {blocks}) as roam, {u(3).replace("(i)", "(n.i)")} * d as x, {u(2).replace("(i)", "(n.i)")} as y from near_ n left join bdeg on bdeg.t = n.u),
steps as materialized (select u, t, m, sum(m) over (partition by u order by t rows unbounded preceding) as high from sym),
props as materialized (select distinct r, s from (select r, least(floor(y * {blocks}), {blocks - 1})::bigint as s from drawn where roam union all select r, t from drawn join steps on steps.u = drawn.u and high - m <= x and x < high where not roam) where r <> s)"""


add("b2_propose_w1", with_model("w1", "alone", lambda e, a, c: merge.propose(c, 25, 4, SEED)), f"{T.model('w1', 'alone')}, {T.near()}, {_OUTER}, {_merge_draws(25, 4, SEED)} select r, s from props")
# The two best merges that are not the same pair: blocks of a tree take its least number, then numbers by least node.
_B5 = f"""{_SCORED}, best as materialized (select r, s, round(d_s, 9) as d, row_number() over (order by round(d_s, 9) desc, r) as k from (select *, row_number() over (partition by r order by round(d_s, 9) desc, s) as j from gain) where j = 1),
one as (select least(r, s) as x, greatest(r, s) as y from best where k = 1), two as (select least(r, s) as x, greatest(r, s) as y from best, one where (least(r, s), greatest(r, s)) <> (one.x, one.y) order by k limit 1),
tree as (select b, case when b in (one.x, one.y, two.x, two.y) and (one.x in (two.x, two.y) or one.y in (two.x, two.y)) then least(one.x, two.x) when b = one.y then one.x when b = two.y then two.x else b end as root from (select distinct b from assign), one, two),
least_ as (select root, min(i) as least from assign join tree using (b) group by root) select i, n as b from assign join tree using (b) join (select root, row_number() over (order by least) - 1 as n from least_) using (root)"""
add("b5_apply_w1", with_model("w1", "region", lambda e, a, c: merge.relabel(a, merge.apply(merge.best_per_block(merge.score(merge.all_pairs(c), c)), 5, 3))), _B5)
add("b5b_apply_distributed_w1", with_model("w1", "region", lambda e, a, c: merge.relabel(a, merge.apply_distributed(relops.settled(merge.best_per_block(merge.score(merge.all_pairs(c), c))), 2))), _B5)
add("b7_relabel_w1", with_model("w1", "region", lambda e, a, c: merge.relabel(a, a.sparkSession.createDataFrame([(4, 0), (3, 1)], "r bigint, root bigint"))), f"with assign as ({T.ASSIGN_SQL['region']}), m as (select i, case b when 4 then 0 when 3 then 1 else b end as b from assign), n as (select b, row_number() over (order by min(i)) - 1 as k from m group by b) select i, k as b from m join n using (b)")
add("contract_cells_w1", with_model("w1", "region", lambda e, a, c: stats.contract(c, a.sparkSession.createDataFrame([(4, 0), (3, 1)], "r bigint, root bigint"))), f"{T.model('w1', 'region')} select case r when 4 then 0 when 3 then 1 else r end as r, case s when 4 then 0 when 3 then 1 else s end as s, sum(m) as m from cells group by all")

# Search
add("s1_start_w1", lambda s, sf: W.each_alone(W.w1(s, sf)), f"with edges as ({W.SQL['w1']}) {T.ASSIGN_SQL['alone']}")


def _schedule(s, sf):
    """The tries of the search while lengths go on falling."""
    out = [500]
    while (b := search.next_try([(x, float(x)) for x in out])) is not None:
        out.append(b)
    return s.createDataFrame(list(enumerate(out)), "k bigint, blocks bigint")


add("s2_schedule", _schedule, "with recursive t(k, blocks) as (select 0::bigint, 500::bigint union all select k + 1, greatest(1, blocks // 2) from t where blocks > 1) select k, blocks from t")


def fitted(graph, **options):
    def call(s, sf):
        edges = W.GRAPHS[graph](s, sf)
        nodes = table(s, sf, "nation", "n_nationkey").select(F.col("n_nationkey").cast("bigint").alias("i")) if graph == "w1" else None
        assign, history = search.fit(edges, nodes, search.FitConfig(**options))
        best = min(history, key=lambda x: (round(x["h_val"], 9), x["B"]))
        out = assign.select("i", "b", F.lit(best["B"]).cast("bigint").alias("blocks"), F.lit(round(best["h_val"], 6)).alias("h_val"))
        return out.join(table(s, sf, "nation", "n_nationkey", "n_name").select(F.col("n_nationkey").cast("bigint").alias("i"), "n_name"), "i") if graph == "w1" else out

    return call


def _null_fit_sql():
    one = f"with edges as materialized ({W.SQL['w1']}), assign as (select n_nationkey::bigint as i, 0::bigint as b from nation), {T.CELLS}"
    return f"{one} select i, b, 1::bigint as blocks, (select h_val from ({T.dl()})) as h_val, n_name from assign join nation on n_nationkey = i"


#: A null control: the answer is one block, whose length SQL can tell.
add("fit_w1", fitted("w1"), _null_fit_sql())
#: Of three roles all five partitions can be told.
_ALL_OF_THREE = f"""with e as materialized ({W.SQL['w8']}), lab as (select p, blocks, unnest([0, 1, 2])::bigint as i, unnest([0, x, y])::bigint as b from (values (0, 1, 0, 0), (1, 2, 0, 1), (2, 2, 1, 0), (3, 2, 1, 1), (4, 3, 1, 2)) v(p, blocks, x, y)),
c as materialized (select a.p, a.b as r, z.b as s, sum(w) as m from e join lab a on a.i = src join lab z on z.i = dst and z.p = a.p group by all),
part as (select p, {sql_phi('m')} as x from c union all select p, -{sql_phi('d')} from (select p, r, sum(m) as d from c group by p, r) union all select p, -{sql_phi('d')} from (select p, s, sum(m) as d from c group by p, s)),
total as (select p, sum(x) as s_val from part group by p), size as (select sum(w) as e from e),
length as (select p, blocks, e * {T.H_OF('(blocks * blocks / e)')} + 3 * ln(blocks) - s_val as h_val from total join (select distinct p, blocks from lab) using (p), size)
select i, b, blocks::bigint as blocks, round(h_val, 6) as h_val from lab join (select p, h_val from length order by round(h_val, 9), blocks limit 1) using (p)"""
add("fit_w8", fitted("w8", restarts=3), _ALL_OF_THREE)


def history_of(s, history):
    return s.createDataFrame([(x["target"], x["B"], round(x["h_val"], 6), round(x["s_val"], 6), x["sweeps"]) for x in history], "target bigint, blocks bigint, h_val double, s_val double, sweeps bigint")


add("s7_history_w1", lambda s, sf: history_of(s, search.fit(W.w1(s, sf))[1]))


def planted_nodes(s, sf, n_table="customer", key="c_custkey"):
    return table(s, sf, n_table, key).select(F.col(key).cast("bigint").alias("i"))


def scored(s, edges, truth, assign, history, directed=True):
    """One row: the fit's blocks and length, the truth's, and all measures of correctness."""
    best = min(history, key=lambda x: (round(x["h_val"], 9), x["B"]))
    counts = stats.cells(edges, truth.withColumnRenamed("t", "b")) if directed else stats.undirected_counts(edges, truth.withColumnRenamed("t", "b"))
    own = relops.settled(truth.withColumnRenamed("t", "b").join(assign.select("i"), "i", "left_semi"))
    known = stats.description_length(relops.settled(counts), own, directed)
    row = metrics.report(truth, assign).crossJoin(known.select(F.round("h_val", 6).alias("truth_h_val")))
    row = row.withColumn("blocks", F.lit(best["B"]).cast("bigint")).withColumn("fit_h_val", F.lit(round(best["h_val"], 6))).withColumn("tries", F.lit(len(history) - 1).cast("bigint"))
    return row.select(*[F.round(c, 6).alias(c) if k == "double" else F.col(c) for c, k in row.dtypes])


def planted_fit(preset, n_table="customer", key="c_custkey", blocks=None, **options):
    def call(s, sf):
        edges, truth = generate.preset(planted_nodes(s, sf, n_table, key), preset, blocks)
        edges, truth = relops.settled(edges), relops.settled(truth)
        assign, history = search.fit(edges, truth.select("i"), search.FitConfig(**options))
        return scored(s, edges, truth, relops.settled(assign), history)

    return call


#: The four panels on all customers; the demonstration on all vectors, in eight blocks.
for _p in generate.PRESETS:
    add(f"fit_w9_{_p}", planted_fit(_p))
add("fit_w14", planted_fit("base", "embeddings", "vec_id", 8))


def history_w14(s, sf):
    """The snapshots of the demonstration: every try, with its numbers of blocks."""
    edges, truth = generate.preset(planted_nodes(s, sf, "embeddings", "vec_id"), "base", 8)
    return history_of(s, search.fit(relops.settled(edges), truth.select("i"))[1])


add("s10_history_w14", history_w14)


def best_w14(s, sf):
    """The try of least length, by SQL over the history as a table."""
    history_w14(s, sf).createOrReplaceTempView("history_w14")
    return s.sql("select min_by(blocks, struct(round(h_val, 9), blocks)) as blocks, min(h_val) as h_val, count(*) as tries from history_w14")


add("s10_best", best_w14)


def fit_distributed(s, sf):
    """The search on Spark alone, on all customers: the whole of it, from each node as its own block, with the sweeps, limits and schedule of the other fits."""
    with relops.few_sent(s):
        edges, truth = generate.preset(planted_nodes(s, sf), "base")
        edges, truth = relops.settled(edges), relops.settled(truth)
        assign, history = search.fit(edges, truth.select("i"), search.FitConfig(engine="spark"))
        return scored(s, edges, truth, relops.settled(assign), history)


add("fit_w9_distributed", fit_distributed)
add("fit_w8_distributed", lambda s, sf: search.fit(W.w8(s, sf), None, search.FitConfig(engine="spark", max_sweeps=2))[0])


def fit_undirected(graph):
    def call(s, sf):
        edges = relops.settled(W.GRAPHS[graph](s, sf))
        assign, history = search.fit(edges, None, search.FitConfig(directed=False))
        assign = relops.settled(assign)
        truth = W.language_of_document(s, sf).withColumnRenamed("b", "t").join(assign.select("i"), "i", "left_semi")
        return scored(s, edges, truth, assign, history, directed=False)

    return call


add("fit_w6_undirected", fit_undirected("w6"))


def fit_hybrid(s, sf):
    """A planted graph on the suppliers within the graph of transitions: one fit of all, scored on the planted part."""
    made, truth = generate.preset(planted_nodes(s, sf, "supplier", "s_suppkey"), "base")
    odd = lambda df, *cs: df.withColumns({c: 2 * F.col(c) + 1 for c in cs})
    real = W.w4(s, sf).select((2 * F.col("src")).alias("src"), (2 * F.col("dst")).alias("dst"), "w")
    both = relops.settled(generate.embed(real, odd(made, "src", "dst")))
    truth = relops.settled(odd(truth, "i"))
    assign, history = search.fit(both.groupBy("src", "dst").agg(F.sum("w").alias("w")))
    best = min(history, key=lambda x: (round(x["h_val"], 9), x["B"]))
    row = metrics.report(truth, relops.settled(assign)).withColumn("blocks", F.lit(best["B"]).cast("bigint")).withColumn("h_val", F.lit(round(best["h_val"], 6)))
    return row.select(*[F.round(c, 6).alias(c) if k == "double" else F.col(c) for c, k in row.dtypes])


add("fit_w10_hybrid", fit_hybrid)


def schedules(s, sf):
    """One start, all schedules: sweeps until each has converged, and what they reach."""
    from blockpart.plans import local

    edges, truth = generate.preset(planted_nodes(s, sf, "embeddings", "vec_id"), "base", 8)
    edges, truth = relops.settled(edges), relops.settled(truth)
    graph = search.to_local(edges, truth)
    own = dict(truth.select("i", "t").collect())
    right = np.array([own[i] for i in graph.ids.tolist()])
    draw = local.draws(SEED, "start", 0, graph.names), local.draws(SEED, "start", 0, graph.names, 1)
    begin = np.where(draw[0] < 0.4, np.floor(draw[1] * 8).astype(np.int64), right)
    rows = []
    for name, cfg in (("sequential", search.FitConfig(schedule="sequential")), ("synchronous", search.FitConfig(schedule="sync")), ("synchronous, half damped", search.FitConfig(schedule="sync", damp=0.5)), ("four batches", search.FitConfig()), ("within four partitions", search.FitConfig(schedule="local", parts=4))):
        cfg.max_sweeps = 12
        if cfg.schedule == "local":
            frame = lambda b: s.createDataFrame(list(zip(graph.ids.tolist(), b.tolist(), strict=True)), "i bigint, b bigint")
            b, past, sweeps = begin, [local.cells(graph, begin, 8).log_posterior()], 0
            while sweeps < cfg.max_sweeps and not sweep.converged(past, cfg.tau_closed):
                now = dict(sweep.partition_local(edges, frame(b), 8, cfg.seed, sweeps, cfg.beta, cfg.parts).collect())
                b = np.array([now[i] for i in graph.ids.tolist()])
                past.append(local.cells(graph, b, 8).log_posterior())
                sweeps += 1
        else:
            b, sweeps = local.LocalEngine(graph, cfg, cfg.seed).settle(begin, cfg.tau_closed)
        engine = local.LocalEngine(graph, search.FitConfig(), SEED)
        b = local.relabel(b)
        s_val, h_val = engine.length(b)
        table_ = np.zeros((8, 8))
        np.add.at(table_, (right, b), 1)
        together = lambda x: float((x * (x - 1) / 2).sum())
        rows.append((name, sweeps, round(s_val, 6), round(h_val, 6), round(engine.length(right)[1], 6), together(table_) / together(table_.sum(0)), together(table_) / together(table_.sum(1))))
    return s.createDataFrame(rows, "schedule string, sweeps bigint, s_val double, h_val double, truth_h_val double, pair_precision double, pair_recall double")


add("w16_schedules", schedules)


def fit_rates(s):
    """Seconds of whole fits on one machine by size: one node after another, and by arrays."""
    from blockpart.plans import local

    rows = []
    for n in (60, 120, 240, 480):
        edges, truth = generate.preset(s.range(n).toDF("i"), "base", 4)
        graph = search.to_local(relops.settled(edges), truth)
        for name, schedule in (("serial", "sequential"), ("arrays", "batched")) if n <= 120 else (("arrays", "batched"),):
            begin = time.monotonic()
            local.fit(graph, schedule=schedule)
            rows.append((name, "fit", 1, n, float(graph.w.sum()), time.monotonic() - begin))
    return rows


def rates(s, sf):
    """Edges a second by size and engine: whole fits on one machine; one sweep on Spark over 1, 2 and 4 partitions."""
    rows, was, n = fit_rates(s), s.conf.get("spark.sql.shuffle.partitions"), 5000
    edges, truth = generate.preset(s.range(n).toDF("i"), "base", 4)
    edges = relops.settled(edges)
    assign = relops.settled(truth.select("i", F.col("t").alias("b")))
    counts, e = relops.settled(stats.cells(edges, assign)), float(edges.agg(F.sum("w")).first()[0])
    try:
        for parts in (1, 2, 4):
            s.conf.set("spark.sql.shuffle.partitions", parts)
            begin = time.monotonic()
            sweep.batched_with(edges, assign, counts, 4, SEED, 0)
            rows.append(("spark", "sweep", parts, n, e, time.monotonic() - begin))
    finally:
        s.conf.set("spark.sql.shuffle.partitions", was)
    return s.createDataFrame([(*r, r[4] / r[5]) for r in rows], RATES + ", rate double")


RATES = "engine string, what string, parallel bigint, nodes bigint, e double, sec double"
add("w13_rates", rates)


def slopes(s, sf):
    """Slope of ln rate against ln edges of each engine, beside that of E log^2 E over the same sizes."""
    out = None
    runs = s.createDataFrame(fit_rates(s), RATES)
    for engine in ("serial", "arrays"):
        row = perf.scaling_fit(runs.where(F.col("engine") == engine)).withColumn("engine", F.lit(engine))
        out = row if out is None else out.unionByName(row)
    return out


add("q9_scaling", slopes)

# Matrix form
add("x1_gamma_w1", with_model("w1", "region", lambda e, a, c: matrix.indicator(a), False), "select n_nationkey::bigint as row, n_regionkey::bigint as col, 1.0::double as v from nation")
add("x3_gag_w1", with_model("w1", "region", lambda e, a, c: matrix.block_counts(e, a), False), f"{T.model('w1', 'region')} select r as row, s as col, m as v from cells")
add("x4_rows_w1", with_model("w1", "region", lambda e, a, c: matrix.row_contrib(e, a), False), f"{T.model('w1', 'region')} select src as row, b as col, sum(w) as v from edges join assign on i = dst group by all")
add("x5_cols_w1", with_model("w1", "region", lambda e, a, c: matrix.col_contrib(e, a), False), f"{T.model('w1', 'region')} select dst as row, b as col, sum(w) as v from edges join assign on i = src group by all")
_STEP1 = f"{T.model('w1', 'region')}, {T.near()}, {T.propose(SEED, 0, 5)}, {T.CHANGE}"
add("x7_dense_tensor_w1", with_model("w1", "region", lambda e, a, c: matrix.tensor(_parts(e, a, c)[4], e, a, c, dense=True)), f"{_STEP1} select v.i, x.t as p, y.t as q, coalesce(m, 0) + coalesce(dm, 0) as m from moving v cross join bdeg x cross join bdeg y left join cells on cells.r = x.t and cells.s = y.t left join chg on chg.i = v.i and chg.p = x.t and chg.q = y.t")
add("x8_sparse_tensor_w1", with_model("w1", "region", lambda e, a, c: matrix.tensor(_parts(e, a, c)[4], e, a, c)), f"{_STEP1} select i, p, q, dm from chg")
_DS = f"{_STEP1}, {T.GAIN} select p.i, round(coalesce(d_s, 0), 6) as d_s from props p left join gain g on g.i = p.i"
for _name, _flags in (("all", {}), ("x10_off", {"skip_same": False, "delta_only": False}), ("x11_off", {"delta_only": False}), ("x13_off", {"touched_only": False})):
    add(f"x9_delta_{_name}_w1", with_model("w1", "region", lambda e, a, c, f=_flags: rounded(matrix.delta_by(_parts(e, a, c)[4], e, a, c, **f), "d_s").withColumn("d_s", F.col("d_s") + 0.0)), _DS)

_CHANCES = "(select k.i as row, x.t as col, sum(k.k / z.k * (coalesce(sym.m, 0) + 1) / (bdeg.d + 5)) as v from kit k join (select i, sum(k) as k from kit group by i) z on z.i = k.i join bdeg on bdeg.t = k.t cross join bdeg x left join sym on sym.u = k.t and sym.t = x.t group by all)"
for _g, _k in (("w1", "region"), ("w4", "mod5")):
    add(f"x6_proposals_{_g}", with_model(_g, _k, lambda e, a, c: rounded(matrix.propose(e, a, c, 5), "v")), f"{T.model(_g, _k)}, {T.near()} select row, col, round(v, 6) as v from {_CHANCES}")
    add(f"x9_accept_{_g}", with_model(_g, _k, lambda e, a, c, p=_parts: rounded(matrix.accept(p(e, a, c)[4], e, a, c, 5, 3.0, SEED, 0), "a")), f"{T.step(_g, _k, SEED, 0, 5)} select i, r, s, round(a, 6) as a, draw < a as accept from decided")

# Generator
_NODES = "(select c_custkey::bigint as i from customer)"
_e = 1.0 - 2.5
_THETA = f"(select i, round(pow(({30.0**_e - 1.0}) * {sql_u01(SEED, 'theta', 0, 'i')} + 1.0, {1.0 / _e}), 9) as theta from {_NODES})"
add("g2_theta_customer", lambda s, sf: rounded(generate.theta_powerlaw(planted_nodes(s, sf), 2.5), "theta"), f"select i, round(theta, 6) as theta from {_THETA}")


def _shares(alpha):
    return f"(select b, round((sum(x) over (order by b rows unbounded preceding) - x) / sum(x) over (), 9) as low, round(sum(x) over (order by b rows unbounded preceding) / sum(x) over (), 9) as high from (select b, round(sum(-ln(1 - {sql_u01(SEED, 'dir', 0, 'b', 'K')})), 9) as x from range(5) t(b), range({alpha}) u(k) group by b))".replace("'K'", "k::varchar")


add("g3_truth_dirichlet", lambda s, sf: generate.truth_dirichlet(planted_nodes(s, sf), 5, 10), f"select i, b as t from {_NODES} join {_shares(10)} on {sql_u01(SEED, 'blk', 0, 'i')} >= low and {sql_u01(SEED, 'blk', 0, 'i')} < high")
add("g4_omega", lambda s, sf: generate.omega(s, 5, 25.0), "select r, s, case when r = s then 25.0 else 1.0 end::double as v from range(5) a(r), range(5) b(s)")


def _theta_sql(nodes, exponent, hi):
    e = 1.0 - exponent
    return f"(select i, round(pow(({hi**e - 1.0}) * {sql_u01(SEED, 'theta', 0, 'i')} + 1.0, {1.0 / e}), 9) as theta from {nodes})"


def _pairwise_sql(nodes, truth, blocks, ratio, exponent, hi):
    """A draw per ordered pair: how many terms of the cumulative distribution are at or below it."""
    draw = sql_u01(SEED, "pois", 0, "src || ':' || dst")
    return f"""with node as materialized (select i, t, theta from {truth} join {_theta_sql(nodes, exponent, hi)} using (i)),
size as (select t, sum(theta) as theta from node group by t), load as (select sum((case when x.t = y.t then {ratio} else 1.0 end) * x.theta * y.theta) as load from size x, size y),
scale as (select round((select count(*) from node) * {generate.DEGREE} / load, 12) as scale from load),
pair as materialized (select x.i as src, y.i as dst, round(scale * (case when x.t = y.t then {ratio} else 1.0 end) * x.theta * y.theta, 9) as rate from node x, node y, scale),
drawn as materialized (select src, dst, rate, {draw} as x from pair),
term as (select src, dst, x, sum(exp(k * ln(rate) - rate - lgamma(k + 1))) over (partition by src, dst order by k rows unbounded preceding) as cdf from drawn, lateral (select unnest(range((ceil(rate + 12 * sqrt(rate)) + 41)::bigint)) as k))
select src, dst, count(*)::double as w from term where round(cdf, 12) <= x group by src, dst"""


#: Pairs of all suppliers: a draw for each is for small graphs only.
_SUPPLIERS = "(select s_suppkey::bigint as i from supplier)"
for _p, (_b, _ratio, _alpha, _exponent, _hi) in generate.PRESETS.items():
    _truth = f"(select i, b as t from {_SUPPLIERS} join {_shares(_alpha)} on {sql_u01(SEED, 'blk', 0, 'i')} >= low and {sql_u01(SEED, 'blk', 0, 'i')} < high)"
    add(f"g6_{_p}_pairwise", lambda s, sf, p=_p: generate.preset(planted_nodes(s, sf, "supplier", "s_suppkey"), p, method="pairwise")[0], _pairwise_sql(_SUPPLIERS, _truth, _b, _ratio, _exponent, _hi))
    add(f"g6_{_p}_blockpair", lambda s, sf, p=_p: generate.preset(planted_nodes(s, sf), p)[0])


def _w9s(s, sf):
    """Suppliers with the region of their nation as truth."""
    rows = table(s, sf, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(table(s, sf, "nation", "n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey"))
    truth = rows.select(F.col("s_suppkey").cast("bigint").alias("i"), F.col("n_regionkey").cast("bigint").alias("t"))
    return generate.planted(truth, generate.theta_powerlaw(truth, 2.5), generate.omega(s, 5, 25.0), 16.0, SEED, "pairwise")


add("g1a_pairwise_w9s", _w9s, _pairwise_sql(_SUPPLIERS, "(select s_suppkey::bigint as i, n_regionkey::bigint as t from supplier join nation on s_nationkey = n_nationkey)", 5, 25.0, 2.5, 30.0))
add("g11_hybrid", lambda s, sf: generate.embed(relops.settled(W.w3(s, sf).select((F.col("src") * 2).alias("src"), (F.col("dst") * 2).alias("dst"), "w")), relops.settled(generate.preset(planted_nodes(s, sf), "base")[0].select((F.col("src") * 2 + 1).alias("src"), (F.col("dst") * 2 + 1).alias("dst"), "w"))).groupBy("part").agg(F.count(F.lit(1)).alias("edges"), F.sum("w").alias("w")))

# Stages
_STAGE = f"(select src, dst, w, (floor({sql_u01(SEED, 'stage', 0, chr(39).join(['src || ', ':', ' || dst']))} * 10) + 1)::int as stage from ({W.SQL['w4']}))"
add("t1_emerging_w4", lambda s, sf: stages.emerging(W.w4(s, sf), 10), f"select * from {_STAGE}")
add("t3_stage_increment", lambda s, sf: stages.only(stages.emerging(W.w4(s, sf), 10), 3), f"select * from {_STAGE} where stage = 3")
add("t1_bytime_w4", lambda s, sf: stages.by_time(table(s, sf, "events", "ts", "user_id"), "ts").groupBy("stage").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("user_id").alias("users")), "select (date_diff('day', (select date_trunc('day', min(ts)) from events), date_trunc('day', ts)) + 1)::int as stage, count(*) as n, count(distinct user_id) as users from events group by 1")
add("t2_snowball_w4", lambda s, sf: stages.snowball(W.w4(s, sf), s.createDataFrame([(1,)], "i bigint"), 3), f"""with recursive e as materialized ({W.SQL['w4']}), both_ as materialized (select src as i, dst as j from e union select dst, src from e),
rings(i, ring) as (select 1::bigint, 0 union select j, ring + 1 from rings join both_ using (i) where ring < 3), first as materialized (select i, min(ring) as ring from rings group by i)
select src, dst, w, greatest(a.ring, b.ring, 1)::int as stage from e join first a on a.i = src join first b on b.i = dst""")
add("stage_diff_w4", lambda s, sf: relops.stage_diff(stages.emerging(W.w4(s, sf), 10), 3, 4), f"with e as materialized {_STAGE} select coalesce(a.src, b.src) as src, coalesce(a.dst, b.dst) as dst, a.w as before, b.w as after from (select * from e where stage <= 3) a full join (select * from e where stage <= 4) b on a.src = b.src and a.dst = b.dst")

# Baselines
for _g, _k in (("w1", "region"), ("w6", "language")):
    add(f"bl4_modularity_{_g}", with_model(_g, _k, lambda e, a, c: rounded(baselines.modularity(e, a), "q"), False), f"{T.model(_g, _k)} select round(sum(coalesce(m, 0) / e - d_out * d_in / (e * e)), 6) as q from bdeg left join cells on r = t and s = t, (select sum(m) as e from cells)")
add("bl4_gamma_w1", with_model("w1", "region", lambda e, a, c: rounded(baselines.modularity(e, a, 0.5), "q"), False), f"{T.model('w1', 'region')} select round(sum(coalesce(m, 0) / e - 0.5 * d_out * d_in / (e * e)), 6) as q from bdeg left join cells on r = t and s = t, (select sum(m) as e from cells)")
_GREEDY = f"""{T.model('w4', 'mod5')}, {T.near()}, tot as (select sum(m) as e from cells),
size as materialized (select i, sum(o) as o, sum(n) as n from (select src as i, w as o, 0.0 as n from edges union all select dst, 0.0, w from edges) group by i),
pull as materialized (select x.i, x.t, a.b as r, (k_out + k_in) / e - (z.o * (d.d_in - case when x.t = a.b then z.n else 0 end) + z.n * (d.d_out - case when x.t = a.b then z.o else 0 end)) / (e * e) as p
  from near x join assign a on a.i = x.i join size z on z.i = x.i join bdeg d on d.t = x.t, tot),
alone as (select a.i, -(z.o * (d.d_in - z.n) + z.n * (d.d_out - z.o)) / (e * e) as p from assign a join size z on z.i = a.i join bdeg d on d.t = a.b, tot),
gains as (select p.i, p.t, round(p.p - coalesce(y.p, l.p), 12) as dq from pull p left join pull y on y.i = p.i and y.t = y.r join alone l on l.i = p.i where p.t <> p.r)
select i, t as s, round(dq, 6) as dq from (select *, row_number() over (partition by i order by dq desc, t) as k from gains where dq > 0) where k = 1"""
add("bl5_greedy_step_w4", with_model("w4", "mod5", lambda e, a, c: rounded(baselines.greedy_gains(e, a), "dq"), False), _GREEDY)
add("bl5_greedy_w1", lambda s, sf: baselines.greedy(relops.settled(W.w1(s, sf)), W.region_of_nation(s, sf)))
add("bl6_power_step_w1", lambda s, sf: rounded(baselines.power_step(W.w1(s, sf), W.region_of_nation(s, sf).select("i", (F.col("i") - 12.0).alias("x"))), "x"), f"with e as materialized ({W.SQL['w1']}), sym as materialized (select src, dst, w / 2 as w from e union all select dst, src, w / 2 from e), deg as (select src as i, sum(w) as k from sym group by 1), tot as (select sum(k) as e, sum(k * (i - 12.0)) as kx from deg) select d.i, round(ax - k * kx / e, 6) as x from deg d join (select src as i, sum(w * (dst - 12.0)) as ax from sym group by 1) s on s.i = d.i, tot")
add("bl6_spectral_w1", lambda s, sf: baselines.spectral(W.w1(s, sf), rounds=6))


def _slices(s, sf):
    rows = table(s, sf, "events", "ts", "user_id", "event_type").select((F.col("user_id") * 4).alias("src"), string_id(F.col("event_type"), 1).alias("dst"), F.dayofmonth("ts").cast("bigint").alias("slice"))
    return rows.groupBy("src", "dst", "slice").agg(F.count(F.lit(1)).cast("double").alias("w"))


def _slice_assign(edges):
    nodes = edges.select(F.col("src").alias("i"), "slice").union(edges.select("dst", "slice")).distinct()
    return nodes.withColumn("b", F.col("i") % 3)


add("bl7_multislice_w4", lambda s, sf: rounded(baselines.multislice(_slices(s, sf), _slice_assign(_slices(s, sf))), "q"), """with e as materialized (select user_id * 4 as src, ('0x' || substr(md5(event_type), 1, 13))::bigint * 4 + 1 as dst, day(ts) as slice, count(*)::double as w from events group by all),
n as materialized (select i, slice, i % 3 as b from (select src as i, slice from e union select dst, slice from e)),
c as materialized (select e.slice, x.b as r, y.b as s, sum(w) as m from e join n x on x.i = src and x.slice = e.slice join n y on y.i = dst and y.slice = e.slice group by all),
tot as (select slice, sum(m) as e from c group by slice), d as (select slice, t, sum(o) as o, sum(n) as n from (select slice, r as t, m as o, 0.0 as n from c union all select slice, s, 0.0, m from c) group by all),
cp as (select count(*) as pairs, count_if(a.b = b.b) as kept from n a join n b on a.i = b.i and b.slice = a.slice + 1)
select round(((select sum(m) from c where r = s) - (select sum(o * n / e) from d join tot using (slice)) + 0.1 * kept) / ((select sum(e) from tot) + 0.1 * pairs), 6) as q from cp""")


def clique_graph(nodes, links):
    """Edges of cliques of nodes(i, c), and links(x, y) in both directions where both ends are nodes."""
    inner = nodes.select(F.col("i").alias("src"), "c").join(nodes.select(F.col("i").alias("dst"), "c"), "c").where("src <> dst").select("src", "dst")
    ends = links.join(nodes.select(F.col("i").alias("x")), "x", "left_semi").join(nodes.select(F.col("i").alias("y")), "y", "left_semi")
    return inner.unionAll(ends.select("x", "y")).unionAll(ends.select("y", "x")).withColumn("w", F.lit(1.0))


def resolution(s, sf):
    """Modularity and description length of clique graphs under their partitions: one merges small cliques, the other keeps them.

    Suppliers by key in groups of two cliques of 12 and one of 150, each two of them linked; customers in a ring of cliques of 5.
    """
    i, c, g, p = F.col("i"), F.col("c"), F.floor(F.col("i") / 174), F.col("i") % 174
    big = planted_nodes(s, sf, "supplier", "s_suppkey").select("i", (3 * g + F.when(p < 12, 0).when(p < 24, 1).otherwise(2)).alias("c"))
    pairs = F.explode(F.array(*[F.struct(F.lit(x).alias("x"), F.lit(y).alias("y")) for x, y in ((0, 12), (0, 24), (12, 24))])).alias("l")
    big_links = big.where(p == 0).select("i", pairs).select((i + F.col("l.x")).alias("x"), (i + F.col("l.y")).alias("y"))
    ring = planted_nodes(s, sf).select("i", F.floor(i / 5).alias("c"))
    of = ring.agg((F.max("c") + 1).alias("of"))
    ring_links = ring.where("i % 5 = 0").crossJoin(F.broadcast(of)).select((5 * c + 1).alias("x"), (5 * ((c + 1) % F.col("of"))).alias("y"))
    out = None
    for name, nodes, links, blocks in (("big_and_small", big, big_links, (c, c - F.when(c % 3 == 1, 1).otherwise(0))), ("ring_5", ring, ring_links, (c, F.floor(c / 2), F.floor(c / 3)))):
        nodes = relops.settled(nodes)
        edges = relops.settled(clique_graph(nodes, links))
        for block in blocks:
            assign = nodes.select("i", block.cast("bigint").alias("b"))
            row = baselines.modularity(edges, assign).crossJoin(stats.description_length(stats.cells(edges, assign), assign))
            row = row.select(F.lit(name).alias("fixture"), F.col("b").cast("bigint").alias("blocks"), F.round("q", 6).alias("q"), F.round("h_val", 6).alias("h_val"))
            out = row if out is None else out.unionAll(row)
    return out


_BIG = "select s_suppkey::bigint as i, 3 * (s_suppkey // 174) + case when s_suppkey % 174 < 12 then 0 when s_suppkey % 174 < 24 then 1 else 2 end as c from supplier"
_RING = "select c_custkey::bigint as i, c_custkey // 5 as c from customer"
_LINKS = {"big": "select i + x as x, i + y as y from clique, (values (0, 12), (0, 24), (12, 24)) t(x, y) where i % 174 = 0", "ring": "select 5 * c + 1 as x, 5 * ((c + 1) % (select max(c) + 1 from clique)) as y from clique where i % 5 = 0"}


def _limit_sql(name, which, cliques, block):
    """Modularity and description length of a partition of cliques that are joined by single links."""
    return f"""(with clique as materialized ({cliques}), link as materialized (select x, y from ({_LINKS[which]}) where x in (select i from clique) and y in (select i from clique)),
assign as materialized (select i, ({block})::bigint as b from clique), edges as materialized (select x.i as src, y.i as dst, 1.0::double as w from clique x join clique y on x.c = y.c and x.i <> y.i union all select x, y, 1.0 from link union all select y, x, 1.0 from link),
{T.CELLS}, q as (select sum(coalesce(m, 0) / e - d_out * d_in / (e * e)) as q from bdeg left join cells on r = t and s = t, (select sum(m) as e from cells))
select '{name}' as fixture, b::bigint as blocks, round(q, 6) as q, h_val from q, ({T.dl()}))"""


add("bl8_resolution_limit", resolution, " union all ".join([_limit_sql("big_and_small", "big", _BIG, "c"), _limit_sql("big_and_small", "big", _BIG, "case c % 3 when 1 then c - 1 else c end"), *(_limit_sql("ring_5", "ring", _RING, f"c // {k}") for k in (1, 2, 3))]))
_WALK = f"""with e as materialized ({W.SQL['w4']}), st as materialized (select src, dst, w / sum(w) over (partition by src) as p from e),
n1 as materialized (select i, sum(x) as x from (select dst as i, 0.85 * p as x from st where src = 1 union all select 1, 0.15) group by i),
n2 as (select i, sum(x) as x from (select dst as i, 0.85 * n1.x * p as x from st join n1 on n1.i = src union all select 1, 0.15) group by i) select i, round(x, 6) as score from n2"""
add("bl10_seed_walk_w4", lambda s, sf: rounded(baselines.seed_walk(W.w4(s, sf), s.createDataFrame([(1,)], "i bigint"), steps=2), "score"), _WALK)
add("bl11_pagerank_w1", lambda s, sf: rounded(relops.pagerank(W.w1(s, sf), 2), "rank"), f"with e as materialized ({W.SQL['w1']}), st as materialized (select src, dst, w / sum(w) over (partition by src) as p from e), n as materialized (select src as i from e union select dst from e), c as (select count(*)::double as c from n), r1 as materialized (select i, 0.15 / c + 0.85 * (coalesce(got, 0) + (1 - (select sum(p / c) from st, c)) / c) as rank from n cross join c left join (select dst as i, sum(p / (select c from c)) as got from st group by 1) using (i)), r2 as (select n.i, 0.15 / c + 0.85 * (coalesce(got, 0) + (1 - (select sum(rank * p) from st join r1 on r1.i = src)) / c) as rank from n cross join c left join (select dst as i, sum(rank * p) as got from st join r1 on r1.i = src group by 1) g on g.i = n.i) select i, round(rank, 6) as rank from r2")
add("bl11_bfs_w4", lambda s, sf: relops.bfs_rings(W.w4(s, sf), s.createDataFrame([(1,)], "i bigint"), 3), f"with recursive e as materialized ({W.SQL['w4']}), both_ as materialized (select src as i, dst as j from e union select dst, src from e), rings(i, ring) as (select 1::bigint, 0 union select j, ring + 1 from rings join both_ using (i) where ring < 3) select i, min(ring)::int as ring from rings group by i")
add("bl12_trivial_w1", lambda s, sf: rounded(stats.description_length(stats.cells(W.w1(s, sf), baselines.trivial(W.region_of_nation(s, sf).select("i"))["one"]), baselines.trivial(W.region_of_nation(s, sf).select("i"))["one"]), "s_val", "model", "labels", "data", "h_val"), f"with edges as materialized ({W.SQL['w1']}), assign as (select n_nationkey::bigint as i, 0::bigint as b from nation), {T.CELLS} {T.dl()}")
