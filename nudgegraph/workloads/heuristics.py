"""Queries over the baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from nudgegraph.operators.baselines import KINDS, degree_global, degree_local, degrees, hop_profile, influence_rank
from nudgegraph.operators.diffusion import hop_layers
from nudgegraph.plans.solvers import allocate_budget, seeds_influential, solve, solve_extra_seeds
from nudgegraph.workloads.sampled import THETA, Setting, greedy_sql, setting_sql

K = 5


def _picks(pick, kind):
    def query(spark, sf_dir):
        s = Setting(spark, sf_dir)
        return s.rows("rank int, node long", list(enumerate(pick(s.problem(K), kind))))

    return query


def _degrees(spark, sf_dir):
    p = Setting(spark, sf_dir).problem(K)
    out = None
    for kind in (1, 3):
        part = degrees(p, kind).select(F.lit(KINDS[kind]).alias("kind"), "node", F.round("score", 6).alias("score"))
        out = part if out is None else out.unionByName(part)
    return out


def _rank(spark, sf_dir):
    return influence_rank(Setting(spark, sf_dir).problem(K), rounds=20).select("node", F.round("rank", 7).alias("rank"))


def _rank_done(spark, sf_dir):
    s = Setting(spark, sf_dir)
    a, b = influence_rank(s.problem(K)), influence_rank(s.problem(K), rounds=30).withColumnRenamed("rank", "r")
    return a.join(b, "node").agg((F.abs(F.sum("rank") - 1) < 1e-6).alias("sums_to_one"), (F.sum(F.abs(F.col("rank") - F.col("r"))) < 2e-3).alias("settled"))


def _extra(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return s.rows("rank int, node long", list(enumerate(solve_extra_seeds(s.problem(3), salt=1, coins="portable", theta=THETA).boost)))


def _hops(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return hop_layers(s.graph, s.seeds).select("node", "hop")


def _profile(spark, sf_dir):
    s = Setting(spark, sf_dir)
    return hop_profile(s.problem(K), s.boost)


def _best_of(spark, sf_dir):
    s = Setting(spark, sf_dir)
    got = solve(s.problem(3), "degree_global", runs=50)
    return s.row("size int, kind_known boolean", len(got.boost), got.report.kind in KINDS)


def _pure(spark, sf_dir):
    s = Setting(spark, sf_dir)
    got = allocate_budget(s.graph, total=4, cost_ratio=3, fractions=(1.0,), runs=50, max_sketches=2000)
    return got.select("fraction", "n_seeds", "n_boosts", "capped", (F.col("spread") >= F.col("n_seeds")).alias("at_least_seeds"))


def _doubling(spark, sf_dir):
    s = Setting(spark, sf_dir)
    a = seeds_influential(s.graph, 2, framework="doubling", max_sketches=4000)
    return s.row("size int", len(a))


QUERIES = {
    **{f"degree_{name if name != 'out' else 'out'}": _picks(degree_global, kind) for kind, name in KINDS.items()},
    **{f"local_{name}": _picks(degree_local, kind) for kind, name in KINDS.items()},
    "degree_scores": _degrees, "influence_rank_20": _rank, "influence_rank_converged_p": _rank_done, "extra_seeds_r": _extra, "hop_layers": _hops, "hop_profile": _profile,
    "degree_best_of_p": _best_of, "pure_seeding_p": _pure, "seeds_doubling_p": _doubling,
}

_HOPS = """, hp as (select x, 0 as t from s union select x, t from (select e.dst as x, hp.t + 1 as t from hp join e on e.src = hp.x where hp.t < 12)),
hop as materialized (select x, min(t) as t from hp group by x)"""
_WEIGHT = {1: "select src as x, dst as y, p as w from e", 3: "select dst as x, src as y, q - p as w from e"}


def _degree_sql(kind: int, local: bool) -> str:
    base = 1 if kind in (1, 2) else 3
    out = setting_sql(1) + _HOPS + f", wt as materialized ({_WEIGHT[base]}), cand as (select n.x{', hop.t' if local else ', 0 as t'} from n {'join hop on hop.x = n.x' if local else ''} where n.x not in (select x from s))"
    picks, gone = [], "select null::bigint as x where false"
    for j in range(K):
        kept = f"where y not in ({gone})" if kind in (2, 4) else ""
        out += f", d{j} as materialized (select c.x, c.t, round(coalesce(sum(v.w), 0), 9) as w from cand c left join (select * from wt {kept}) v on v.x = c.x where c.x not in ({gone}) group by c.x, c.t order by c.t, w desc, c.x limit 1)"
        gone = " union all ".join(f"select x from d{i}" for i in range(j + 1))
        picks.append(f"select {j}::integer as rank, x as node from d{j}")
    return out + " " + " union all ".join(picks)


def _rank_sql(rounds: int) -> str:
    out = setting_sql(1) + """, rho as (select dst as u, sum(p) as r from e group by dst), mv as materialized (select e.dst as u, e.src as v, p / r as w from e join rho on rho.u = e.dst),
k0 as materialized (select x, 1.0::double / n as rank, n from n)"""
    for j in range(rounds):
        out += f""", k{j + 1} as materialized (select k.x, 0.15::double / k.n + 0.85::double * (select coalesce(sum(rank), 0) from k{j} where x not in (select u from rho)) / k.n + 0.85::double * coalesce(f.f, 0) as rank, k.n
from k{j} k left join (select v, sum(w * rank) as f from mv join k{j} on k{j}.x = mv.u group by v) f on f.v = k.x)"""
    return out + f" select x as node, round(rank, 7) as rank from k{rounds}"


ORACLES = {
    **{f"degree_{name}": _degree_sql(kind, False) for kind, name in KINDS.items()},
    **{f"local_{name}": _degree_sql(kind, True) for kind, name in KINDS.items()},
    "degree_scores": setting_sql(1) + """ select k.kind, n.x as node, round(coalesce(d.w, 0), 6) as score from n cross join (values ('out'), ('in_gain')) k(kind)
      left join (select 'out' as kind, src as x, sum(p) as w from e group by src union all select 'in_gain', dst, sum(q - p) from e group by dst) d on d.kind = k.kind and d.x = n.x where n.x not in (select x from s)""",
    "influence_rank_20": _rank_sql(20),
    "influence_rank_converged_p": "select true as sums_to_one, true as settled",
    "extra_seeds_r": greedy_sql(setting_sql(THETA), "select i, x from z where x not in (select x from s) and i not in (select i from z where x in (select x from s))", 3, False),
    "hop_layers": setting_sql(1) + _HOPS + " select x as node, t::integer as hop from hop",
    "hop_profile": setting_sql(1) + _HOPS + " select t::integer as hop, count(*) as n from b left join hop on hop.x = b.x group by t",
    "degree_best_of_p": "select 3::integer as size, true as kind_known",
    "pure_seeding_p": "select 1.0::double as fraction, 4::integer as n_seeds, 0::integer as n_boosts, false as capped, true as at_least_seeds",
    "seeds_doubling_p": "select 2::integer as size",
}
