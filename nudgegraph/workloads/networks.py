"""Queries over the networks: builders, statistics, components, probabilities."""

from __future__ import annotations

from pyspark.sql import functions as F

from nudgegraph.model import BoostGraph, with_boost
from nudgegraph.operators.components import components
from nudgegraph.plans.planner import from_actions
from nudgegraph.sources import networks as net
from nudgegraph.workloads import sql


def r6(df, *columns):
    return df.withColumns({c: F.round(c, 6) for c in columns})


def largest_wcc(edges):
    """The edges of the largest weakly connected component; ties to the smaller id."""
    member = components(edges, "src", "dst")
    top = member.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1).select("component")
    inside = member.join(F.broadcast(top), "component", "left_semi").select(F.col("node").alias("src"))
    return edges.join(inside, "src", "left_semi")


def graph_stats(edges):
    """One row: nodes, edges, mean chance."""
    nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).agg(F.count_distinct("node").alias("n"))
    return edges.agg(F.count("*").alias("m"), F.round(F.avg("p"), 6).alias("avg_p")).crossJoin(F.broadcast(nodes)).select("n", "m", "avg_p")


def trivalent_parts(spark, sf_dir):
    return net.trivalency(net.two_way(net.tree_parts(spark, sf_dir)))


def _stats(spark, sf_dir):
    made = {"customers": net.net_customers, "events_6h": net.net_events, "suppliers": net.net_suppliers}
    out = None
    for name, build in made.items():
        row = graph_stats(build(spark, sf_dir)).withColumn("net", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def _events_48h(spark, sf_dir):
    made = net.event_networks(spark, sf_dir, (48, 1.0))[0]
    return r6(made.listed().select("src", "dst", "p") if from_actions(made) else made, "p")


def _parallel_edges(spark, sf_dir):
    made = net.event_networks(spark, sf_dir, (6, 4.0), (48, 1.0))
    if not from_actions(made[0]):
        made = with_boost(made[0].unionByName(made[1]))
    return r6(net.merge_parallel(made, "noisy_or"), "p", "q")


QUERIES = {
    "net_customers": lambda s, d: r6(net.net_customers(s, d), "p"),
    "net_customers_90d": lambda s, d: r6(net.net_customers(s, d, 90), "p"),
    "net_events_6h": lambda s, d: r6(net.net_events(s, d), "p"),
    "net_events_48h": _events_48h,
    "net_suppliers": lambda s, d: r6(net.net_suppliers(s, d), "p"),
    "net_embeddings_knn": lambda s, d: r6(net.net_embeddings(s, d), "p"),
    "net_conversations": lambda s, d: r6(net.net_conversations(s, d), "p"),
    "net_pages_hosts": lambda s, d: r6(net.net_pages(s, d), "p"),
    "tree_parts": net.tree_parts,
    "tree_geography": net.tree_geography,
    "forest_orders": net.forest_orders,
    "largest_component": lambda s, d: r6(largest_wcc(net.net_customers(s, d, 90)), "p"),
    "graph_statistics": _stats,
    "boosted_probabilities": lambda s, d: r6(with_boost(with_boost(net.net_events(s, d)).withColumnRenamed("q", "q2"), 3.0).withColumnRenamed("q", "q3"), "p", "q2", "q3"),
    "trivalency_tree": trivalent_parts,
    "dense_node_numbers": lambda s, d: BoostGraph.from_edges(net.net_customers(s, d)).nodes,
    "graph_faults": lambda s, d: net.check_graph(with_boost(net.net_suppliers(s, d)).unionByName(s.createDataFrame([(1, 1, 0.5, 0.4), (None, 2, 0.1, 0.2)], "src long, dst long, p double, q double"))),
    "parallel_edges_noisy_or": _parallel_edges,
}

_BASE = "select src, dst, round(p, 6) as p from ({})"
_NODES = "select src as x from e union select dst from e"

ORACLES = {
    "net_customers": _BASE.format(sql.customers()),
    "net_customers_90d": _BASE.format(sql.customers(90)),
    "net_events_6h": _BASE.format(sql.events()),
    "net_events_48h": _BASE.format(sql.events(48, 1.0)),
    "net_suppliers": _BASE.format(sql.SUPPLIERS),
    "net_embeddings_knn": _BASE.format(sql.EMBEDDINGS),
    "net_conversations": _BASE.format(sql.CONVERSATIONS),
    "net_pages_hosts": f"with {sql.PAGES_WITH} {_BASE.format(sql.PAGES)}",
    "tree_parts": sql.TREE_PARTS,
    "tree_geography": sql.TREE_GEO,
    "forest_orders": sql.FOREST,
    "largest_component": f"""with recursive e as materialized ({sql.customers(90)}), b as (select src as a, dst as b from e union select dst, src from e),
      reach as (select x, x as o from ({_NODES}) union select b.b, reach.o from reach join b on b.a = reach.x),
      lab as (select x, min(o) as c from reach group by x), top as (select c from lab group by c order by count(*) desc, c limit 1)
      select src, dst, round(p, 6) as p from e where src in (select x from lab where c = (select c from top))""",
    "graph_statistics": "with c as materialized ({}), v as materialized ({}), s as materialized ({}) ".format(sql.customers(), sql.events(), sql.SUPPLIERS)
    + " union all ".join(f"select '{n}' as net, (select count(*) from (select src from {t} union select dst from {t})) as n, count(*) as m, round(avg(p), 6) as avg_p from {t}" for n, t in (("customers", "c"), ("events_6h", "v"), ("suppliers", "s"))),
    "boosted_probabilities": f"select src, dst, round(p, 6) as p, round(1 - (1 - p) * (1 - p), 6) as q2, round(1 - (1 - p) * (1 - p) * (1 - p), 6) as q3 from ({sql.events()})",
    "trivalency_tree": sql.trivalent(sql.TREE_PARTS),
    "dense_node_numbers": f"with e as materialized ({sql.customers()}) select x as node, row_number() over (order by x) - 1 as idx from ({_NODES})",
    "graph_faults": "select 'loop' as fault, 1::bigint as n union all select 'raised below base', 1 union all select 'null id', 1",
    "parallel_edges_noisy_or": f"""with e as (select * from ({sql.events()}) union all select * from ({sql.events(48, 1.0)})), q as (select src, dst, p, 1 - (1 - p) * (1 - p) as q from e)
      select src, dst, round(1 - exp(sum(case when p < 1 then ln(1 - p) else -800 end)), 6) as p, round(1 - exp(sum(case when q < 1 then ln(1 - q) else -800 end)), 6) as q from q group by src, dst""",
}
