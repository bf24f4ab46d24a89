"""Queries with coins: diffusion, reach sets, sketches, selections.

All use portable coins, so their SQL twins replay the very same worlds. Twins
work by reachability in worlds and never build a sketch.
"""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from nudgegraph.model import BoostProblem
from nudgegraph.operators.diffusion import boost_mc, simulate, spread_exact_of, spread_mc
from nudgegraph.operators.sketches import (
    critical_incidence, critical_shares, delta_hat, equivalence_faults, head_incidence, marginal_counts, mu_hat, nu_hat, reach_sets, sample_sketches, sandwich_scatter, select_marginal, sketch_stats,
)
from nudgegraph.plans.solvers import seeds_influential, seeds_random, solve, spread_reach
from nudgegraph.plans.stopping import cover_greedy, required_sketches, run_doubling, run_martingale
from nudgegraph.session import Scratch
from nudgegraph.sources import networks as net
from nudgegraph.workloads import sql

#: values may lie on a border of rounding: both engines round a hair above them
HAIR = 1e-12
THETA, RUNS, CAP, TIGHT, LOOSE = 300, 60, 1000, 2, 1.0
# fixed: worked examples as (src, dst, p, q)
PATH = [(0, 1, 0.2, 0.4), (1, 2, 0.1, 0.2)]
STAR = [(a, b, 0.1, 0.19) for x in (1, 2, 3) for a, b in ((0, x), (x, 0))]
COVER = [(0, c, 0.5, 1.0) for c in (1, 2, 3)] + [(c, x, 1.0, 1.0) for c, xs in ((1, (4, 5, 6)), (2, (5, 6, 7)), (3, (7, 8, 9))) for x in xs]
GATE = [(0, 1, 0.5, 1.0), (1, 2, 0.5, 1.0), (0, 2, 0.5, 1.0), (2, 3, 0.5, 1.0)]
# the same shapes with the place of each edge's chance; None is a sure edge
PATH_SHAPE = [(0, 1, 0), (1, 2, 1)]
STAR_SHAPE = [(a, b, x - 1) for x in (1, 2, 3) for a, b in ((0, x), (x, 0))]
COVER_SHAPE = [(0, c, c - 1) for c in (1, 2, 3)] + [(c, x, None) for c, x, *_ in COVER if c]
GATE_SHAPE = [(0, 1, 0), (1, 2, 1), (0, 2, 2), (2, 3, 3)]
COVER_SETS = [(), (1,), (2,), (1, 2), (1, 3)]
GATE_SETS = [(3,)]
PATH_SETS = [(), (1,), (2,), (1, 2)]
STAR_SETS = [(), (0,), (2,), (0, 2)]


class Setting:
    """The network of events with its seeds and a fixed set to boost."""

    def __init__(self, spark, sf_dir):
        self.spark, self.graph = spark, net.events_graph(spark, sf_dir)
        self.seeds = seeds_random(self.graph, max(2, self.graph.n // 30), 0)
        self.boost = sorted(set(seeds_random(self.graph, 20, 3)) - set(self.seeds))

    def problem(self, k):
        return BoostProblem(self.graph, self.spark.createDataFrame([(s,) for s in self.seeds], "node long"), k)

    def sketches(self, theta=THETA, cap=CAP, **more):
        return Scratch(self.spark, "sketches").keep(sample_sketches(self.graph, self.seeds, 0, theta, cap, 1, "portable", **more), "rows")

    def row(self, schema, *values):
        return self.spark.createDataFrame([values], schema)

    def rows(self, schema, values):
        return self.spark.createDataFrame(values, schema)


def _mc(mode):
    def query(spark, sf_dir):
        s = Setting(spark, sf_dir)
        return boost_mc(s.graph, s.seeds, s.boost, RUNS, salt=1, mode=mode, coins="portable").select(F.round("delta", 6).alias("delta"), F.round("stderr", 6).alias("stderr"))

    return query


def _spread(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return spread_mc(s.graph, s.seeds, s.boost, RUNS, salt=1, coins="portable").select(F.round("spread", 6).alias("spread"), F.round("stderr", 6).alias("stderr"))


def _steps(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return simulate(s.graph, s.seeds, s.boost, RUNS, salt=1, coins="portable").groupBy("step").agg(F.count("*").alias("n"))


def _exact_of(shape, seeds, sets):
    """By year of ordering, on the shape with the year's shares as chances."""

    def query(spark, sf_dir):
        got = spread_exact_of(net.order_shares(spark, sf_dir), shape, seeds, sets)
        return got.select("graph", "boost", F.round(F.col("spread") + HAIR, 9).alias("spread"), F.round(F.col("delta") + HAIR, 9).alias("delta"))

    return query


def _exact_sql(spread, sets):
    rows = " union all ".join(f"select graph, '{' '.join(map(str, b))}' as boost, {spread(b)} as spread, {spread(())} as plain from g" for b in sets)
    return f"with g as materialized ({sql.ORDER_SHARES}) select graph, boost, round(spread + {HAIR}, 9) as spread, round(spread - plain + {HAIR}, 9) as delta from ({rows})"


def _reach_sets(spark, sf_dir):
    return reach_sets(Setting(spark, sf_dir).graph, 0, THETA, 1, "portable")


def _reach_spread(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return s.row("spread double", round(spread_reach(reach_sets(s.graph, 0, THETA, 1, "portable"), s.seeds, s.graph.n, THETA), 6))


def _seeds_influential(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return s.rows("rank int, node long", list(enumerate(seeds_influential(s.graph, 3, salt=1, coins="portable", theta=THETA))))


def _seeds_random(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return s.rows("node long", [(v,) for v in s.seeds])


def _required(spark, sf_dir):
    """By year of ordering: sketches for the year's customers as nodes, and a hundredth of its orders as the best value."""
    orders = net.table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").cast("long").alias("graph"))
    sizes = orders.agg(F.count_distinct("o_custkey").alias("n"), (F.count("*") / 100).alias("opt")).withColumn("k", F.least("n", F.lit(10)))
    rows = [(r.graph, r.n, r.k, r.opt, required_sketches(r.n, r.k, 0.5, 1.0, r.opt)) for r in sizes.collect()]
    return spark.createDataFrame(rows, "graph long, n long, k long, opt double, theta long")


def _categories(spark, sf_dir):
    return Setting(spark, sf_dir).sketches().select("sketch", "root", "category")


def _critical(spark, sf_dir):
    return critical_incidence(Setting(spark, sf_dir).sketches())


def _touched(spark, sf_dir):
    return Setting(spark, sf_dir).sketches().select("sketch", "n_touched")


def _estimates(spark, sf_dir):
    s = Setting(spark, sf_dir)
    k = s.sketches()
    return s.row("delta double, mu double", round(delta_hat(k, s.boost, s.graph.n, THETA), 6), round(mu_hat(k, s.boost, s.graph.n, THETA), 6))


def _one(which):
    def query(spark, sf_dir):
        return _estimates(spark, sf_dir).select(which)

    return query


def _nu(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return s.row("nu double", round(nu_hat(s.sketches(cap=TIGHT), s.boost, s.graph.n, THETA), 6))


def _marginal(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return marginal_counts(s.sketches(), s.boost[:3])


def _compression(spark, sf_dir):
    s = Setting(spark, sf_dir)
    faults = equivalence_faults(s.graph, s.seeds, 0, THETA, CAP, [s.boost, s.boost[:2], s.boost[:1], []], 1, "portable")
    grown = s.sketches().where("n_edges > n_raw_edges").count()
    return s.row("faults long, grown long", faults, grown)


def _compressed(spark, sf_dir):
    """Edges before and after compression of sketches that two boosts may open."""
    return Setting(spark, sf_dir).sketches(cap=TIGHT).where("category = 'boostable'").select("sketch", "n_raw_edges", "n_edges")


def _pruned(spark, sf_dir):
    """Categories and edges examined where ways that need two boosts are pruned."""
    return Setting(spark, sf_dir).sketches(cap=1).select("sketch", "category", "n_touched")


def _heads_rows(spark, sf_dir):
    return head_incidence(Setting(spark, sf_dir).sketches(cap=TIGHT))


def _capped_critical(spark, sf_dir):
    return critical_incidence(Setting(spark, sf_dir).sketches(keep="critical"))


def _no_compression(spark, sf_dir):
    """The direct greedy on sketches that keep all their edges: compression must not change its picks."""
    s = Setting(spark, sf_dir)
    picks = select_marginal(s.sketches(squeeze=False), 2, s.seeds)
    return s.rows("rank int, node long, gain long", [(i, v, c) for i, (v, c) in enumerate(picks)])


def _cap_equal(spark, sf_dir):
    s = Setting(spark, sf_dir)
    a, b = critical_incidence(s.sketches()), critical_incidence(s.sketches(keep="critical"))
    return s.row("only_full long, only_capped long", a.exceptAll(b).count(), b.exceptAll(a).count())


def _strategies(spark, sf_dir):
    s = Setting(spark, sf_dir)
    a, b = (sample_sketches(s.graph, s.seeds, 0, 20, 2, 1, "portable", how) for how in ("local", "relational"))
    return s.row("only_local long, only_relational long", a.exceptAll(b).count(), b.exceptAll(a).count())


def _lower(spark, sf_dir):
    s = Setting(spark, sf_dir)
    picks = cover_greedy(critical_incidence(s.sketches()), 3, set(s.seeds))
    return s.rows("rank int, node long, gain long", [(i, v, c) for i, (v, c) in enumerate(picks)])


def _direct(spark, sf_dir):
    s = Setting(spark, sf_dir)
    picks = select_marginal(s.sketches(), 2, s.seeds)
    return s.rows("rank int, node long, gain long", [(i, v, c) for i, (v, c) in enumerate(picks)])


def _solver(method):
    """The returned set with the estimates and the ratio that the report gives it."""

    def query(spark, sf_dir):
        s = Setting(spark, sf_dir)
        got = solve(s.problem(2), method, theta=THETA, coins="portable")
        r = got.report.values
        values = [round(float(r.get(c, 0.0)), 6) for c in ("delta_hat", "mu_hat", "nu_hat", "lower_ratio", "upper_ratio", "guarantee")]
        return s.rows("rank int, node long, chosen string, delta double, mu double, nu double, lower_ratio double, upper_ratio double, guarantee double", [(i, v, r.get("chosen", "lower"), *values) for i, v in enumerate(got.boost)])

    return query


def _martingale(spark, sf_dir):
    """Influential seeds with the number of reach sets that the stopping rule calls for."""
    s = Setting(spark, sf_dir)
    scratch = Scratch(spark, "rule")
    got = run_martingale(lambda lo, hi: reach_sets(s.graph, lo, hi, 1, "portable"), lambda df: df, lambda df: scratch.keep(df, "sets"), s.graph.n, 2, LOOSE, 1.0)
    picks = cover_greedy(got.sketches, 2)
    return s.rows("rank int, node long, theta long, lower double", [(i, v, got.theta, round(got.lower, 6)) for i, (v, _) in enumerate(picks)])


def _doubling(spark, sf_dir):
    """The same by doubling two halves until the second confirms the first one's picks."""
    s = Setting(spark, sf_dir)
    scratch = Scratch(spark, "rule")
    got = run_doubling(lambda lo, hi: reach_sets(s.graph, lo, hi, 1, "portable"), lambda df: df, lambda df: scratch.keep(df, "sets"), s.graph.n, 2, LOOSE, 1.0, 1 << 20)
    picks = cover_greedy(got.sketches, 2)
    return s.rows("rank int, node long, theta long, lower double", [(i, v, got.theta, round(got.lower, 6)) for i, (v, _) in enumerate(picks)])


def _ratio(spark, sf_dir):
    """Share of the boost that the lower bound explains; not a number where no sketch shows a boost, as in SQL."""
    share = F.coalesce(F.try_divide("mu", "delta"), F.lit(float("nan")))
    return _estimates(spark, sf_dir).select(F.round(share, 5).alias("ratio"))


def _scatter(spark, sf_dir):
    s = Setting(spark, sf_dir)
    k = s.sketches()
    others = [r.node for r in s.problem(1).candidates().orderBy("node").collect()]
    points = sandwich_scatter(k, s.boost, others, s.graph.n, THETA)
    return points.agg((F.count("*") > 0).alias("some"), (F.max("ratio") <= 1).alias("at_most_one"), (F.min("ratio") > 0).alias("above_zero"))


def _shares(spark, sf_dir):
    s = Setting(spark, sf_dir)
    got = critical_shares(s.sketches(), s.boost)
    return got.select("n", *[F.round(c, 6).alias(c) for c in ("with_critical", "critical_boosted", "critical_not_boosted")])


def _category_shares(spark, sf_dir):
    return sketch_stats(Setting(spark, sf_dir).sketches()).select("theta", *[F.round(c, 6).alias(c) for c in ("activated", "hopeless", "boostable", "raw_edges", "critical_nodes", "touched")])


def _heads(spark, sf_dir):
    s = Setting(spark, sf_dir)
    h, c = head_incidence(s.sketches()), critical_incidence(s.sketches())
    return s.row("critical_without_head long", c.exceptAll(h).count())


QUERIES = {
    "spread_mc_r": _spread, "boost_mc_r": _mc("receiver"), "sender_mode_mc_r": _mc("sender"), "single_boost_mc_r": _mc("single_boost"), "activation_steps_r": _steps,
    "exact_spread_path": _exact_of(PATH_SHAPE, {0}, PATH_SETS), "exact_spread_star": _exact_of(STAR_SHAPE, {1, 3}, STAR_SETS),
    "exact_spread_cover": _exact_of(COVER_SHAPE, {0}, COVER_SETS), "exact_spread_gate": _exact_of(GATE_SHAPE, {0}, GATE_SETS),
    "reach_sets_r": _reach_sets, "reach_spread_r": _reach_spread, "seeds_influential_r": _seeds_influential, "seeds_random": _seeds_random, "required_sketches": _required,
    "sketch_categories_r": _categories, "sketch_critical_r": _critical, "sketch_ept_r": _touched, "delta_hat_r": _one("delta"), "mu_hat_r": _one("mu"), "nu_hat_r": _nu,
    "marginal_counts_r": _marginal, "sketch_compression_p": _compression, "sketch_compression_r": _compressed, "sketch_pruning_r": _pruned, "upper_bound_sets_r": _heads_rows, "critical_only_r": _capped_critical, "select_direct_uncompressed_r": _no_compression, "critical_cap_equals_full_p": _cap_equal, "strategies_agree_p": _strategies, "heads_cover_critical_p": _heads, "sketch_statistics_r": _category_shares,
    "select_lower_bound_r": _lower, "select_direct_r": _direct, "solve_full_r": _solver("sketch_full"), "solve_critical_r": _solver("sketch_critical"), "solve_sandwich_r": _solver("sandwich"), "seeds_martingale_r": _martingale, "seeds_doubling_r": _doubling,
    "sandwich_ratio_r": _ratio, "sandwich_scatter_p": _scatter, "critical_shares_r": _shares,
}


def setting_sql(worlds: int, boost_limit: int | None = None) -> str:
    """Edges, nodes, seeds, boosts, worlds with coins; live (l) and raised (r) edges of each world."""
    some = "" if boost_limit is None else f" limit {boost_limit}"
    return f"""with recursive e as materialized ({sql.raised(sql.events())}),
n as materialized (select x, row_number() over (order by x) - 1 as idx, count(*) over () as n from (select src as x from e union select dst from e)),
s as materialized (select x from (select x, row_number() over (order by {sql.coin(1000, '0', 'x')}, x) as r, n from n) where r <= greatest(2, n // 30)),
b as materialized (select x from (select x, row_number() over (order by {sql.coin(1003, '0', 'x')}, x) as r from n) where r <= 20 and x not in (select x from s) order by x{some}),
w as materialized (select range as i from range({worlds})),
c as materialized (select i, src, dst, tp, tq, {sql.coin(1, 'i', 'src', 'dst')} as h from w, e),
l as materialized (select i, src, dst from c where h < tp),
r as materialized (select i, src, dst from c where h >= tp and h < tq),
k as materialized (select i, x as root from w join n on n.idx = {sql.coin(1, "'root'", 'i')} % n.n),
f as (select i, x from w, s union select l.i, l.dst from f join l on l.i = f.i and l.src = f.x),
z as (select i, root as x from k union select l.i, l.src from z join l on l.i = z.i and l.dst = z.x)"""


_ACTIVE = """, act as materialized (select k.i from k join f on f.i = k.i and f.x = k.root),
crit as materialized (select distinct r.i, r.dst as x from r join f on f.i = r.i and f.x = r.src join z on z.i = r.i and z.x = r.dst where r.i not in (select i from act))"""
_ANY = """, a as (select i, x from w, s union select c.i, c.dst from a join (select i, src, dst from l union all select i, src, dst from r) c on c.i = a.i and c.src = a.x)"""
_HELPED = """, hf as (select i, x from w, s union select c.i, c.dst from hf join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from b)) c on c.i = hf.i and c.src = hf.x),
hit as materialized (select k.i from k join hf on hf.i = k.i and hf.x = k.root where k.i not in (select i from act))"""


def _mc_sql(reach: str) -> str:
    return setting_sql(RUNS) + f""", g as ({reach}),
d as (select w.i, (select count(distinct x) from g where g.i = w.i) - (select count(*) from f where f.i = w.i) as d from w)
select round(avg(d), 6) as delta, round(stddev_samp(d) / sqrt(count(*)), 6) as stderr from d"""


_RECEIVER = "select i, x from w, s union select c.i, c.dst from g join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from b)) c on c.i = g.i and c.src = g.x"
_SENDER = _RECEIVER.replace("where dst in", "where src in")
_SINGLE = "select i, x, 0 as y from w, s union select c.i, c.dst, g.y + c.y from g join (select i, src, dst, 0 as y from l union all select i, src, dst, 1 from r where dst in (select x from b)) c on c.i = g.i and c.src = g.x and g.y + c.y <= 1"


def greedy_sql(prefix: str, incidence: str, k: int, gain: bool) -> str:
    """Greedy cover unrolled: the pick, then what it covers, k times."""
    out = prefix + f", inc as materialized ({incidence})"
    covered = "select null::bigint as i where false"
    picks = []
    for j in range(k):
        out += f", p{j} as materialized (select x, count(distinct i) as n from inc where i not in ({covered}) group by x order by n desc, x limit 1)"
        covered = " union ".join(f"select i from inc where x = (select x from p{q})" for q in range(j + 1))
        picks.append(f"select {j}::integer as rank, x as node{', n as gain' if gain else ''} from p{j}")
    return out + " " + " union all ".join(picks)


def _log_choose(n, k):
    return f"(lgamma({n} + 1) - lgamma({k} + 1) - lgamma({n} - {k} + 1))"


def _required_sql():
    e = math.e
    need = f"ceil(2 * n * pow((1 - 1 / {e}) * sqrt(ln(n) + ln(2)) + sqrt((1 - 1 / {e}) * ({_log_choose('n', 'k')} + ln(n) + ln(2))), 2) / (0.25 * opt))::bigint"
    rows = "select year(o_orderdate)::bigint as graph, count(distinct o_custkey)::double as n, least(count(distinct o_custkey), 10)::double as k, count(*) / 100.0::double as opt from orders group by 1"
    return f"select graph, n::bigint as n, k::bigint as k, opt, {need} as theta from ({rows})"


_EST = setting_sql(THETA) + _ACTIVE + _HELPED + f""", est as (select (select max(n) from n) * (select count(*) from hit)::double / {THETA} as delta,
  (select max(n) from n) * (select count(distinct i) from crit where x in (select x from b))::double / {THETA} as mu)"""
_TOUCH = """, q0 as (select i, root as x, 0 as hop from k where root not in (select x from s) union
    select i, x, hop from (select l.i, l.src as x, q0.hop + 1 as hop from q0 join l on l.i = q0.i and l.dst = q0.x where l.src not in (select x from s) and q0.hop < 25)),
qm as materialized (select i, x, min(hop) as hop from q0 group by i, x),
stop as materialized (select i, arg_min(hop, (hop, x, src)) as hop, arg_min(x, (hop, x, src)) as x, arg_min(src, (hop, x, src)) as src
  from (select qm.i, qm.hop, qm.x, l.src from qm join l on l.i = qm.i and l.dst = qm.x where l.src in (select x from s)) group by i),
q1 as (select i, root as x from k union select c.i, c.src from q1 join (select i, src, dst from l union all select i, src, dst from r) c on c.i = q1.i and c.dst = q1.x where q1.x not in (select x from s)),
deg as (select dst as x, count(*) as d from e group by dst),
t as (select qm.i, count(*) as n from qm join stop on stop.i = qm.i join e on e.dst = qm.x where (qm.hop, qm.x, e.src) <= (stop.hop, stop.x, stop.src) group by qm.i
  union all select i, sum(case when q1.x in (select x from s) then 0 else d end) as n from q1 join deg on deg.x = q1.x where i not in (select i from act) group by i),
touch as materialized (select k.i, coalesce(t.n, 0)::bigint as n from k left join t on t.i = k.i),
raw as materialized (select k.i, (select count(*) from qm where qm.i = k.i) - 1 + coalesce(m.n, 0) as n from k left join
  (select c.i, count(*) as n from c join q1 on q1.i = c.i and q1.x = c.dst left join qm on qm.i = c.i and qm.x = c.src where c.h < c.tq and q1.x not in (select x from s) and qm.x is null group by c.i) m on m.i = k.i)"""


def shape_sql(cap: int) -> str:
    """What lies on ways from the seeds to the root that need at most ``cap`` boosts, for sketches that aren't activated."""
    return f""", nb as materialized (select i, src, dst, 0 as y from l union all select i, src, dst, 1 from r),
fx as materialized (select distinct f.i, f.x from f where f.i not in (select i from act)),
zx as materialized (select distinct z.i, z.x from z where z.i not in (select i from act)),
bd as (select i, root as x, 0 as d from k where i not in (select i from act) union
  select i, x, d from (select nb.i, nb.src as x, bd.d + nb.y as d from bd join nb on nb.i = bd.i and nb.dst = bd.x where bd.d + nb.y <= {cap}) q where not exists (select 1 from fx where fx.i = q.i and fx.x = q.x)),
bm as materialized (select i, x, min(d) as d from bd group by i, x),
fd as (select i, x, 0 as d from fx union
  select nb.i, nb.dst, fd.d + nb.y from fd join nb on nb.i = fd.i and nb.src = fd.x where fd.d + nb.y <= {cap} and not exists (select 1 from zx where zx.i = fd.i and zx.x = fd.x)),
fm as materialized (select i, x, min(d) as d from fd group by i, x),
near as materialized (select bm.i, bm.x from bm join fm on fm.i = bm.i and fm.x = bm.x where bm.d + fm.d <= {cap} and not exists (select 1 from fx where fx.i = bm.i and fx.x = bm.x)
  union select k.i, k.root from k where exists (select 1 from zx join fm on fm.i = zx.i and fm.x = zx.x where zx.i = k.i and fm.d <= {cap})),
able as materialized (select distinct i from near),
ways as materialized (select distinct nb.i, case when fx.x is not null then -1 else nb.src end as u, nb.dst as v, nb.y from nb join near v on v.i = nb.i and v.x = nb.dst left join fx on fx.i = nb.i and fx.x = nb.src
  where fx.x is not null or (exists (select 1 from near n where n.i = nb.i and n.x = nb.src) and not exists (select 1 from zx where zx.i = nb.i and zx.x = nb.src))),
head as materialized (select distinct i, v as x from ways where y = 1)"""


_CATEGORY = """, cat as materialized (select k.i, k.root, case when k.i in (select i from act) then 'activated' when exists (select 1 from a where a.i = k.i and a.x = k.root) then 'boostable' else 'hopeless' end as category from k)"""
_DIRECT = setting_sql(THETA) + _ACTIVE + """, p0 as materialized (select x, count(*) as n from crit where x not in (select x from s) group by x order by n desc, x limit 1),
f1 as (select i, x from w, s union select c.i, c.dst from f1 join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from p0)) c on c.i = f1.i and c.src = f1.x),
z1 as (select i, root as x from k union select c.i, c.src from z1 join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from p0)) c on c.i = z1.i and c.dst = z1.x),
a1 as (select k.i from k join f1 on f1.i = k.i and f1.x = k.root),
m1 as (select distinct r.i, r.dst as x from r join f1 on f1.i = r.i and f1.x = r.src join z1 on z1.i = r.i and z1.x = r.dst where r.i not in (select i from a1) and r.dst not in (select x from p0)),
p1 as (select x, count(*) as n from m1 where x not in (select x from s) group by x order by n desc, x limit 1)
select 0::integer as rank, x as node, n as gain from p0 union all select 1::integer, x, n from p1"""


def _reach_sql(name: str, boosted: str) -> str:
    """Sketches that boosting the set activates, as ``name``."""
    return f""", {name}r as (select i, x from w, s union select c.i, c.dst from {name}r join (select i, src, dst from l union all select i, src, dst from r where dst in ({boosted})) c on c.i = {name}r.i and c.src = {name}r.x),
{name} as materialized (select k.i from k join {name}r on {name}r.i = k.i and {name}r.x = k.root where k.i not in (select i from act))"""


def _greedy_ctes(name: str, incidence: str, k: int) -> str:
    out, covered = f", {name}inc as materialized ({incidence})", "select null::bigint as i where false"
    for j in range(k):
        out += f", {name}{j} as materialized (select x, count(distinct i) as n from {name}inc where i not in ({covered}) group by x order by n desc, x limit 1)"
        covered = " union ".join(f"select i from {name}inc where x = (select x from {name}{q})" for q in range(j + 1))
    return out


def solver_sql(sets: tuple[str, ...]) -> str:
    """Two picks by each rule on the same sketches, the better set, and its estimates."""
    out = _DIRECT[: _DIRECT.rindex("select 0::integer")].rstrip()
    out += _greedy_ctes("g", "select i, x from crit where x not in (select x from s)", 2)
    picks = {"lower": "select 0 as j, x from g0 union all select 1, x from g1", "direct": "select 0 as j, x from p0 union all select 1, x from p1"}
    if "upper" in sets:
        out += shape_sql(2) + _greedy_ctes("u", "select i, x from head where x not in (select x from s)", 2)
        picks["upper"] = "select 0 as j, x from u0 union all select 1, x from u1"
    for name in sets:
        out += _reach_sql(f"h{name}", f"select x from ({picks[name]})")
    rows = " union all ".join(f"select '{name}' as chosen, {i} as nth, (select count(*) from h{name}) as n" for i, name in enumerate(sets))
    out += f", sets as ({rows}), best as (select chosen, n from sets order by n desc, nth limit 1), picks as ({' union all '.join(f'select {chr(39)}{name}{chr(39)} as chosen, * from ({picks[name]})' for name in sets)})"
    out += f", mine as (select j, x from picks where chosen = (select chosen from best)), m as (select (select max(n) from n) / {THETA}.0::double as f, (select n from best) as d, (select count(distinct i) from crit where x in (select x from mine)) as l"
    out += ", (select count(distinct i) from head where x in (select x from picks where chosen = 'upper')) as t, (select n from sets where chosen = 'upper') as td)" if "upper" in sets else ", null as t, null as td)"
    keep = f"{1 - 1 / math.e - 0.5}"
    return out + f""" select j::integer as rank, x as node, best.chosen, round(f * d, 6) as delta, round(f * l, 6) as mu, round(coalesce(f * t, 0), 6) as nu, round(l / d::double, 6) as lower_ratio,
      round(case when t is null then 0 else td / t::double end, 6) as upper_ratio, round({keep} * l / d, 6) as guarantee from mine, best, m"""


def _critical_solver_sql() -> str:
    out = setting_sql(THETA) + _ACTIVE + _greedy_ctes("g", "select i, x from crit where x not in (select x from s)", 2)
    return out + f""", m as (select (select n from g0) + (select n from g1) as l), picks as (select 0 as j, x from g0 union all select 1, x from g1)
      select j::integer as rank, x as node, 'lower' as chosen, 0.0::double as delta, round((select max(n) from n) * l / {THETA}.0::double, 6) as mu, 0.0::double as nu, 0.0::double as lower_ratio, 0.0::double as upper_ratio, 0.0::double as guarantee from picks, m"""


_WORLDS = 12_000


def _trial_sql(guess: str, eps: float) -> str:
    e = math.sqrt(2) * eps
    return f"ceil((2 + 2 * {e} / 3) * ({_log_choose('n', 'least(2, n)')} + ln(n) + ln(greatest(ln(greatest(n, 4)) / ln(2), 2))) * n / ({e * e} * ({guess})))"


def _first_worlds(condition: str) -> str:
    """Two covering picks of the reach sets that meet the condition, and how many they cover."""
    return f"select i, x from z where {condition}"


def martingale_sql(rounds: int = 8) -> str:
    """Guesses n/2, n/4, ... until the cover confirms one, then the number of reach sets that it calls for."""
    e, root = math.e, math.sqrt(2) * LOOSE
    out = setting_sql(_WORLDS) + ", nn as materialized (select max(n)::double as n from n)"
    tests = []
    for i in range(1, rounds + 1):
        out += f", th{i} as materialized (select greatest({_trial_sql(f'n / {2**i}', LOOSE)}, {f'(select t from th{i - 1})' if i > 1 else 0})::bigint as t, n / {2**i} as guess, n from nn)"
        out += _greedy_ctes(f"m{i}x", f"select i, x from z where i < (select t from th{i})", 2)
        tests.append(f"select {i} as nth, guess, t, n * ((select n from m{i}x0) + (select n from m{i}x1)) / t as value from th{i} where {i} < greatest(2, ceil(ln(greatest(n, 4)) / ln(2)))")
    need = f"ceil(2 * n * pow((1 - 1 / {e}) * sqrt(ln(n) + ln(2)) + sqrt((1 - 1 / {e}) * ({_log_choose('n', 'least(2, n)')} + ln(n) + ln(2))), 2) / ({LOOSE * LOOSE} * low))"
    out += f""", trials as materialized ({' union all '.join(tests)}), won as materialized (select * from trials where value >= (1 + {root}) * guess order by nth limit 1),
low as materialized (select coalesce((select value / (1 + {root}) from won), 1.0) as low, coalesce((select t from won), (select max(t) from trials)) as done, (select n from nn) as n),
need as materialized (select greatest({need}, done)::bigint as theta, low from low)"""
    out += _greedy_ctes("fin", "select i, x from z where i < (select theta from need)", 2)
    return out + " select 0::integer as rank, (select x from fin0) as node, theta, round(low, 6) as lower from need union all select 1::integer, (select x from fin1), theta, round(low, 6) from need"


def doubling_sql(rounds: int = 5) -> str:
    """Halves of 1, 2, 4, ... times the first size; the first pair that agrees ends it."""
    half, most = 1 << 20, 4_000
    out = setting_sql(most).replace("w as materialized (select range as i from range(%d))" % most, f"w as materialized (select range as i from range({most}) union all select range from range({half}, {half + most}))")
    out += f", nn as materialized (select max(n)::double as n from n), t0 as materialized (select greatest(64, {_trial_sql('n / 2', LOOSE)})::bigint as t from nn)"
    rows = []
    for j in range(rounds):
        out += _greedy_ctes(f"a{j}x", f"select i, x from z where i < {2**j} * (select t from t0)", 2)
        out += f""", v{j} as materialized (select {j} as nth, {2**j} * t as theta, n, n * ((select n from a{j}x0) + (select n from a{j}x1)) / ({2**j} * t) as claimed,
  (select count(distinct i) from z where i >= {half} and i < {half} + {2**j} * (select t from t0) and x in (select x from a{j}x0 union all select x from a{j}x1)) as hit from t0, nn)"""
        rows.append(f"select v{j}.*, n * hit / theta as seen, (select x from a{j}x0) as x0, (select x from a{j}x1) as x1 from v{j}")
    out += f", good as (select * from ({' union all '.join(rows)}) where hit >= 1 + (2 + 2 * {LOOSE} / 3) * ln(2 * greatest(n, 2)) / {LOOSE * LOOSE} and claimed <= (1 + {LOOSE}) * seen order by nth limit 1)"
    return out + f" select 0::integer as rank, x0 as node, theta, round(greatest(1.0, seen / (1 + {LOOSE})), 6) as lower from good union all select 1::integer, x1, theta, round(greatest(1.0, seen / (1 + {LOOSE})), 6) from good"


_MARGINAL = setting_sql(THETA, 3) + _ACTIVE + """, f1 as (select i, x from w, s union select c.i, c.dst from f1 join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from b)) c on c.i = f1.i and c.src = f1.x),
z1 as (select i, root as x from k union select c.i, c.src from z1 join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from b)) c on c.i = z1.i and c.dst = z1.x),
a1 as (select k.i from k join f1 on f1.i = k.i and f1.x = k.root)
select r.dst as node, count(distinct r.i) as n from r join f1 on f1.i = r.i and f1.x = r.src join z1 on z1.i = r.i and z1.x = r.dst
where r.i not in (select i from a1) and r.dst not in (select x from b) group by r.dst"""

ORACLES = {
    "spread_mc_r": setting_sql(RUNS) + f""", g as ({_RECEIVER}), d as (select i, count(*) as d from g group by i)
      select round(avg(d), 6) as spread, round(stddev_samp(d) / sqrt(count(*)), 6) as stderr from d""",
    "boost_mc_r": _mc_sql(_RECEIVER), "sender_mode_mc_r": _mc_sql(_SENDER), "single_boost_mc_r": _mc_sql(_SINGLE),
    "activation_steps_r": setting_sql(RUNS) + """, g as (select i, x, 0 as t from w, s union
        select i, x, t from (select c.i, c.dst as x, g.t + 1 as t from g join (select i, src, dst from l union all select i, src, dst from r where dst in (select x from b)) c on c.i = g.i and c.src = g.x where g.t < 12))
      select t::integer as step, count(*) as n from (select i, x, min(t) as t from g group by i, x) group by t""",
    "exact_spread_path": _exact_sql(sql.path_spread, PATH_SETS),
    "exact_spread_star": _exact_sql(sql.star_spread, STAR_SETS),
    "exact_spread_cover": _exact_sql(sql.cover_spread, COVER_SETS),
    "exact_spread_gate": _exact_sql(sql.gate_spread, GATE_SETS),
    "reach_sets_r": setting_sql(THETA) + " select i as sketch, x as node from z",
    "reach_spread_r": setting_sql(THETA) + f" select round((select max(n) from n) * count(distinct i)::double / {THETA}, 6) as spread from z where x in (select x from s)",
    "seeds_influential_r": greedy_sql(setting_sql(THETA), "select i, x from z", 3, False),
    "seeds_random": setting_sql(1) + " select x as node from s",
    "required_sketches": _required_sql(),
    "sketch_categories_r": setting_sql(THETA) + _ACTIVE + _ANY + _CATEGORY + " select i as sketch, root, category from cat",
    "sketch_critical_r": setting_sql(THETA) + _ACTIVE + " select i as sketch, x as node from crit",
    "sketch_ept_r": setting_sql(THETA) + _ACTIVE + _TOUCH + " select i as sketch, n as n_touched from touch",
    "delta_hat_r": _EST + " select round(delta, 6) as delta from est", "mu_hat_r": _EST + " select round(mu, 6) as mu from est",
    "nu_hat_r": setting_sql(THETA) + _ACTIVE + shape_sql(TIGHT) + f" select round((select max(n) from n) * count(distinct i) / {THETA}.0::double, 6) as nu from head where x in (select x from b)",
    "upper_bound_sets_r": setting_sql(THETA) + _ACTIVE + shape_sql(TIGHT) + " select i as sketch, x as node from head",
    "critical_only_r": setting_sql(THETA) + _ACTIVE + " select i as sketch, x as node from crit",
    "select_direct_uncompressed_r": _DIRECT,
    "sketch_compression_r": setting_sql(THETA) + _ACTIVE + shape_sql(TIGHT) + f""", ph as (select i, root as x, 0 as d from k where i not in (select i from act) union
        select nb.i, nb.src, ph.d + nb.y from ph join nb on nb.i = ph.i and nb.dst = ph.x where ph.d + nb.y <= {TIGHT} and ph.x not in (select x from s)), pm as materialized (select i, x, min(d) as d from ph group by i, x),
      met as (select c.i, count(*) as n from c join pm on pm.i = c.i and pm.x = c.dst left join zx on zx.i = c.i and zx.x = c.src
        where c.i in (select i from able) and (c.h < c.tp or (c.h < c.tq and pm.d + 1 <= {TIGHT})) and zx.x is null and pm.x not in (select x from s) group by c.i)
      select k.i as sketch, (select count(*) from zx where zx.i = k.i) - 1 + coalesce(met.n, 0) as n_raw_edges,
        ((select count(*) from ways where ways.i = k.i) + (select count(*) from zx join near on near.i = zx.i and near.x = zx.x where zx.i = k.i and zx.x <> k.root))::integer as n_edges
      from k left join met on met.i = k.i where k.i in (select i from able)""",
    "sketch_pruning_r": setting_sql(THETA) + _ACTIVE + _TOUCH + """, pd as (select i, root as x, 0 as d from k union
        select c.i, c.src, pd.d + c.y from pd join (select i, src, dst, 0 as y from l union all select i, src, dst, 1 from r) c on c.i = pd.i and c.dst = pd.x where pd.d + c.y <= 1 and pd.x not in (select x from s)),
      pm as materialized (select distinct i, x from pd), pt as (select pm.i, sum(deg.d)::bigint as n from pm join deg on deg.x = pm.x where pm.x not in (select x from s) group by pm.i)
      select k.i as sketch, case when k.i in (select i from act) then 'activated' when exists (select 1 from pm where pm.i = k.i and pm.x in (select x from s)) then 'boostable' else 'hopeless' end as category,
        case when k.i in (select i from act) then touch.n else coalesce(pt.n, 0) end as n_touched from k join touch on touch.i = k.i left join pt on pt.i = k.i""",
    "marginal_counts_r": _MARGINAL,
    "sketch_compression_p": "select 0::bigint as faults, 0::bigint as grown",
    "critical_cap_equals_full_p": "select 0::bigint as only_full, 0::bigint as only_capped",
    "strategies_agree_p": "select 0::bigint as only_local, 0::bigint as only_relational",
    "heads_cover_critical_p": "select 0::bigint as critical_without_head",
    "sketch_statistics_r": setting_sql(THETA) + _ACTIVE + _ANY + _TOUCH + _CATEGORY + """, g as (select cat.*, (select count(*) from crit where crit.i = cat.i) as nc, touch.n as nt, raw.n as ne from cat join touch on touch.i = cat.i join raw on raw.i = cat.i)
      select count(*) as theta, round(avg((category = 'activated')::integer), 6) as activated, round(avg((category = 'hopeless')::integer), 6) as hopeless, round(avg((category = 'boostable')::integer), 6) as boostable,
        round(avg(ne) filter (category = 'boostable'), 6) as raw_edges, round(avg(nc) filter (category = 'boostable'), 6) as critical_nodes, round(avg(nt), 6) as touched from g""",
    "select_lower_bound_r": greedy_sql(setting_sql(THETA) + _ACTIVE, "select i, x from crit where x not in (select x from s)", 3, True),
    "select_direct_r": _DIRECT,
    "solve_full_r": solver_sql(("lower", "direct")), "solve_sandwich_r": solver_sql(("lower", "direct", "upper")), "solve_critical_r": _critical_solver_sql(),
    "seeds_martingale_r": martingale_sql(), "seeds_doubling_r": doubling_sql(),
    "sandwich_ratio_r": _EST + " select round(round(mu, 6) / round(delta, 6), 5) as ratio from est",
    "sandwich_scatter_p": "select true as some, true as at_most_one, true as above_zero",
    "critical_shares_r": setting_sql(THETA) + _ACTIVE + _HELPED + """, g as (select hit.i, hit.i in (select i from crit) as any_, hit.i in (select i from crit where x in (select x from b)) as met from hit)
      select count(*) as n, round(coalesce(avg(any_::integer), 0), 6) as with_critical, round(coalesce(avg(met::integer), 0), 6) as critical_boosted, round(coalesce(avg((any_ and not met)::integer), 0), 6) as critical_not_boosted from g""",
}
