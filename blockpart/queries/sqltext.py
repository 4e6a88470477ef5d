"""SQL texts of the methods' steps, as chained common table expressions for DuckDB."""

from __future__ import annotations

from blockpart.functions.math import sql_phi, sql_u01
from blockpart.sources.workloads import ASSIGN_SQL, SQL

CELLS = """cells as materialized (select a.b as r, c.b as s, sum(w) as m from edges join assign a on a.i = src join assign c on c.i = dst group by all),
bdeg as materialized (select t, sum(o) as d_out, sum(n) as d_in, sum(o + n) as d from (select r as t, m as o, 0.0 as n from cells union all select s, 0.0, m from cells) group by t)"""


def model(graph: str, assign: str) -> str:
    """Edges, assign, cells and bdeg; assign may also be a query of its own over edges."""
    return f"with edges as materialized ({SQL[graph]}), assign as materialized ({ASSIGN_SQL.get(assign, assign)}), {CELLS}"


S_VAL = f"(select sum(x) from (select {sql_phi('m')} as x from cells union all select -{sql_phi('d_out')} - {sql_phi('d_in')} from bdeg))"


def near(b_sql: str = "(select count(distinct b) from assign)") -> str:
    return """near as materialized (select x.i, a.b as t, sum(o) as k_out, sum(n) as k_in from (select src as i, dst as j, w as o, 0.0 as n from edges where src <> dst union all select dst, src, 0.0, w from edges where src <> dst) x join assign a on a.i = x.j group by all),
selfs as materialized (select src as i, sum(w) as w_self from edges where src = dst group by src),
kit as materialized (select i, t, sum(k) as k from (select i, t, k_out + k_in as k from near union all select s.i, a.b, 2 * w_self from selfs s join assign a on a.i = s.i) group by all),
sym as materialized (select u, t, sum(m) as m from (select r as u, s as t, m from cells union all select s, r, m from cells) group by all)"""


def pick(seed: int, it: int) -> str:
    return f"""picked as materialized (select i, arg_min(t, -ln(1 - {sql_u01(seed, 'prop', it, "i || ':' || t", 0)}) / k) as u from kit group by i)"""


def propose(seed: int, it: int, blocks: int, explore: float | None = None) -> str:
    chance = f"{float(blocks)} / (d + {blocks})" if explore is None else str(explore)
    return f"""{pick(seed, it)},
drawn as materialized (select p.i, a.b as r, p.u, {sql_u01(seed, 'prop', it, 'p.i', 1)} < {chance} as roam, {sql_u01(seed, 'prop', it, 'p.i', 3)} * d as x from picked p join assign a on a.i = p.i join bdeg on bdeg.t = p.u),
steps as materialized (select u, t, sum(m) over (partition by u order by t rows unbounded preceding) - m as low, sum(m) over (partition by u order by t rows unbounded preceding) as high from sym),
props as materialized (select i, r, u, least(floor({sql_u01(seed, 'prop', it, 'i', 2)} * {blocks}), {blocks - 1})::bigint as s, 'uniform' as kind from drawn where roam
  union all select i, r, drawn.u, t, 'neighbour' from drawn join steps on steps.u = drawn.u and low <= x and x < high where not roam)"""


CHANGE = """moving as materialized (select i, r, s from props where r <> s),
chg as materialized (select i, p, q, sum(dm) as dm from (
  select m.i, r as p, t as q, -k_out as dm from moving m join near n on n.i = m.i union all select m.i, s, t, k_out from moving m join near n on n.i = m.i
  union all select m.i, t, r, -k_in from moving m join near n on n.i = m.i union all select m.i, t, s, k_in from moving m join near n on n.i = m.i
  union all select m.i, r, r, -w_self from moving m join selfs z on z.i = m.i union all select m.i, s, s, w_self from moving m join selfs z on z.i = m.i) group by all having sum(dm) <> 0)"""

GAIN = f"""size as materialized (select i, sum(k_out) as k_out, sum(k_in) as k_in from (select i, k_out, k_in from near union all select i, w_self, w_self from selfs) group by i),
part as materialized (select c.i, sum({sql_phi('coalesce(m, 0) + dm')} - {sql_phi('coalesce(m, 0)')}) as x from chg c left join cells on cells.r = c.p and cells.s = c.q group by c.i),
gain as materialized (select v.i, v.r, v.s, z.k_out, z.k_in, coalesce(x, 0) - ({sql_phi('a.d_out - z.k_out')} - {sql_phi('a.d_out')} + {sql_phi('b.d_out + z.k_out')} - {sql_phi('b.d_out')} + {sql_phi('a.d_in - z.k_in')} - {sql_phi('a.d_in')} + {sql_phi('b.d_in + z.k_in')} - {sql_phi('b.d_in')}) as d_s
  from moving v join size z on z.i = v.i join bdeg a on a.t = v.r join bdeg b on b.t = v.s left join part on part.i = v.i)"""


def hastings(blocks: int) -> str:
    return f"""ahead as (select k.i, sum(k) as k_i, sum(k * (coalesce(m, 0) + 1) / (d + {blocks})) as f from kit k join gain g on g.i = k.i join bdeg on bdeg.t = k.t left join sym on sym.u = g.s and sym.t = k.t group by k.i),
k2 as (select i, t, sum(k) as k from (select k.i, k.t, k.k from kit k join gain g on g.i = k.i union all select g.i, g.r, -2 * w_self from gain g join selfs z on z.i = g.i union all select g.i, g.s, 2 * w_self from gain g join selfs z on z.i = g.i) group by all having sum(k) <> 0),
shift as (select i, t, r, sum(dm) as dm from (select i, p as t, q as r, dm from chg union all select i, q, p, dm from chg) group by all),
behind as (select k2.i, sum(k2.k * (coalesce(m, 0) + coalesce(dm, 0) + 1) / (d - case when k2.t = g.r then g.k_out + g.k_in else 0 end + case when k2.t = g.s then g.k_out + g.k_in else 0 end + {blocks})) as b
  from k2 join gain g on g.i = k2.i join bdeg on bdeg.t = k2.t left join sym on sym.u = g.r and sym.t = k2.t left join shift h on h.i = k2.i and h.t = k2.t and h.r = g.r group by k2.i),
chance as materialized (select a.i, f / k_i as p_fwd, b / k_i as p_bwd from ahead a join behind using (i))"""


def decide(seed: int, it: int, beta: float) -> str:
    return f"""decided as materialized (select g.*, p_fwd, p_bwd, round(least(1.0, exp(greatest(-700.0, least(700.0, {beta} * round(d_s, 9)))) * p_bwd / p_fwd), 9) as a, {sql_u01(seed, 'acc', it, 'g.i')} as draw from gain g join chance c on c.i = g.i)"""


def step(graph: str, assign: str, seed: int, it: int, blocks: int, beta: float = 3.0, explore: float | None = None) -> str:
    return ", ".join([model(graph, assign), near(), propose(seed, it, blocks, explore), CHANGE, GAIN, hastings(blocks), decide(seed, it, beta)])


H_OF = lambda x: f"({sql_phi(f'1.0 + {x}')} - {sql_phi(x)})"


def dl(directed: bool = True) -> str:
    cells = "b * b" if directed else "b * (b + 1) / 2.0"
    return f"select n, e, b, round(s, 6) as s_val, round(e * {H_OF(f'(({cells}) / e)')}, 6) as model, round(n * ln(b), 6) as labels, round(-s, 6) as data, round(e * {H_OF(f'(({cells}) / e)')} + n * ln(b) - s, 6) as h_val from (select (select count(*)::double from assign) as n, (select count(distinct b)::double from assign) as b, (select sum(m) from cells) * {1.0 if directed else 0.5} as e, {S_VAL if directed else S_UND} as s)"


S_UND = f"(select sum(x) from (select 0.5 * {sql_phi('m')} as x from cells union all select -{sql_phi('d_out')} from bdeg))"


def undirected(graph: str, assign: str) -> str:
    return model(graph, assign).replace("edges as materialized (", "one as materialized (", 1).replace(", assign as", ", edges as materialized (select src, dst, w from one union all select dst, src, w from one), assign as", 1)
