"""Queries over the relational operators, functions and sources."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin, threshold
from nudgegraph.functions.registry import register, sketch_activates, sketch_marginal_nodes
from nudgegraph.model import with_boost
from nudgegraph.operators.relational import asof_join, heavy_hitters, interval_join, leave_one_out, noisy_or, range_join, salted_join, top_per_group
from nudgegraph.session import delete_path, scratch_path
from nudgegraph.sources import networks as net
from nudgegraph.sources.networks import table
from nudgegraph.sources.tables import append_runs, literal_graph, read_edges, save_clustered, write_edges
from nudgegraph.workloads import sql
from nudgegraph.workloads.sampled import Setting

QUERIES: dict = {}
ORACLES: dict = {}


def query(oracle: str | None = None):
    def take(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return take


def micros(ts):
    """Microseconds since 1970 of a time with or without zone."""
    column = F.col(ts) if isinstance(ts, str) else ts
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01").cast("timestamp_ntz"), column.cast("timestamp_ntz"))


def _events(s, d):
    return table(s, d, "events").select("event_id", "user_id", "event_type", "value", "props", "ts", (micros("ts") / 3.6e9).alias("hour"))


_H = "(epoch_us(ts) / 3.6e9)::double"
_EDGES = f"({sql.events()})"


@query("select c_custkey, count(*) as n, round(sum(o_totalprice), 2) as spent from customer join orders on c_custkey = o_custkey group by c_custkey")
def join_inner(s, d):
    return table(s, d, "customer").join(table(s, d, "orders").hint("merge"), F.col("c_custkey") == F.col("o_custkey")).groupBy("c_custkey").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("spent"))


@query("select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
def join_broadcast(s, d):
    return table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@query("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 200000)")
def join_semi(s, d):
    return table(s, d, "customer").join(table(s, d, "orders").where("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 200000)")
def join_anti(s, d):
    return table(s, d, "customer").join(table(s, d, "orders").where("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("select coalesce(c_nationkey, s_nationkey) as nation, count(distinct c_custkey) as customers, count(distinct s_suppkey) as suppliers from (select * from customer where c_acctbal > 9000) full join (select * from supplier where s_acctbal > 5000) on c_nationkey = s_nationkey group by 1")
def join_full_outer(s, d):
    c, p = table(s, d, "customer").where("c_acctbal > 9000"), table(s, d, "supplier").where("s_acctbal > 5000")
    return c.join(p, F.col("c_nationkey") == F.col("s_nationkey"), "full").groupBy(F.coalesce("c_nationkey", "s_nationkey").alias("nation")).agg(F.count_distinct("c_custkey").alias("customers"), F.count_distinct("s_suppkey").alias("suppliers"))


@query("select r_name, count(n_nationkey) as n from region left join nation on r_regionkey = n_regionkey and n_name like '%A%' group by r_name")
def join_left_outer(s, d):
    return table(s, d, "region").join(table(s, d, "nation").where("n_name like '%A%'"), F.col("r_regionkey") == F.col("n_regionkey"), "left").groupBy("r_name").agg(F.count("n_nationkey").alias("n"))


@query("select a.r_name as a, b.r_name as b from region a, region b where a.r_regionkey < b.r_regionkey")
def join_cross_small(s, d):
    r = table(s, d, "region")
    return r.select(F.col("r_name").alias("a"), F.col("r_regionkey").alias("x")).crossJoin(F.broadcast(r.select(F.col("r_name").alias("b"), F.col("r_regionkey").alias("y")))).where("x < y").select("a", "b")


@query(f"select u.event_id as a, v.event_id as b from events u join events v on u.event_type = v.event_type and u.user_id = v.user_id where epoch_us(v.ts) > epoch_us(u.ts) and {_H.replace('ts', 'v.ts')} - {_H.replace('ts', 'u.ts')} <= 6")
def join_range(s, d):
    e = _events(s, d)
    a, b = e.select("user_id", "event_type", F.col("event_id").alias("a"), F.col("hour").alias("h")), e.select("user_id", "event_type", F.col("event_id").alias("b"), F.col("hour").alias("g"))
    return range_join(a, b, ["user_id", "event_type"], "h", "g", 6.0).select("a", "b")


_ASOF = f"""select u.event_id, v.value as value_asof from (select * from events where event_type = 'click') u
  asof left join (select user_id, ts, max(value) as value from events where event_type = 'view' group by user_id, ts) v on u.user_id = v.user_id and u.ts >= v.ts"""


def _sides(s, d):
    e = _events(s, d)
    left = e.where("event_type = 'click'").select("event_id", "user_id", "hour")
    return left, e.where("event_type = 'view'").groupBy("user_id", "hour").agg(F.max("value").alias("value"))


@query(_ASOF)
def join_asof(s, d):
    left, right = _sides(s, d)
    return asof_join(left, right, "user_id", "hour", ["value"]).select("event_id", "value_asof")


@query(f"select event_id, case when gap <= 12 then value_asof end as value_asof from (select u.event_id, {_H.replace('ts', 'u.ts')} - {_H.replace('ts', 'v.ts')} as gap, v.value as value_asof from (select * from events where event_type = 'click') u asof left join (select user_id, ts, max(value) as value from events where event_type = 'view' group by user_id, ts) v on u.user_id = v.user_id and u.ts >= v.ts)")
def join_asof_sliced(s, d):
    left, right = _sides(s, d)
    return asof_join(left, right, "user_id", "hour", ["value"], tolerance=12.0, slice_=6.0).select("event_id", "value_asof")


@query(f"""with x as (select user_id as u, event_type as t, min({_H}) as since, min({_H}) + 2 + user_id % 5 as until from events group by user_id, event_type)
  select a.u as a, b.u as b, a.t as t, b.t as r from x a join x b on a.since < b.until and b.since < a.until and a.t = 'view' and b.t = 'error'""")
def join_interval(s, d):
    x = _events(s, d).groupBy(F.col("user_id").alias("u"), F.col("event_type").alias("t")).agg(F.min("hour").alias("since")).withColumn("until", F.col("since") + 2 + F.col("u") % 5)
    got = interval_join(x.where("t = 'view'"), x.where("t = 'error'"), 4.0)
    return got.select(F.col("u").alias("a"), F.col("r_u").alias("b"), "t", F.col("r_t").alias("r"))


@query(f"select e.src, count(*) as n, round(sum(f.p), 6) as p from {_EDGES} e join {_EDGES} f on e.dst = f.src group by e.src")
def join_salted(s, d):
    e = net.net_events(s, d)
    heavy = e.groupBy("dst").count().where("count > 10").select("dst")
    two = salted_join(e.select("src", "dst"), e.select(F.col("src").alias("dst"), F.col("dst").alias("to"), "p"), "dst", heavy, 4)
    return two.groupBy("src").agg(F.count("*").alias("n"), F.round(F.sum("p"), 6).alias("p"))


@query(f"select e.src, t.dst, round(t.p, 6) as p from (select distinct src from {_EDGES}) e, lateral (select dst, p from {_EDGES} x where x.src = e.src order by p desc, dst limit 2) t")
def join_lateral_top(s, d):
    net.net_events(s, d).createOrReplaceTempView("lateral_edges")
    return s.sql("select e.src, t.dst, round(t.p, 6) as p from (select distinct src from lateral_edges) e, lateral (select dst, p from lateral_edges x where x.src = e.src order by p desc, dst limit 2) t")


@query(f"select dst, round(1 - exp(sum(ln(1 - p))), 6) as reached, count(distinct src) as n from {_EDGES} where p < 1 group by dst")
def agg_noisy_or(s, d):
    return net.net_events(s, d).where("p < 1").groupBy("dst").agg(F.round(noisy_or(F.col("p")), 6).alias("reached"), F.count_distinct("src").alias("n"))


@query(f"select src, dst, round(1 - exp(sum(ln(1 - p)) over (partition by dst) - ln(1 - p)), 6) as others from {_EDGES} where p < 1")
def window_leave_one_out(s, d):
    return net.net_events(s, d).where("p < 1").withColumn("others", F.round(leave_one_out("p", "dst"), 6)).select("src", "dst", "others")


@query("select abs(a - e) <= 0.1 * e as close from (select count(distinct user_id)::double as e, count(distinct user_id)::double as a from events)")
def agg_approx_distinct(s, d):
    return table(s, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("e")).select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("close"))


@query("select user_id, count(*) as n from events group by user_id having count(*) >= 0.008 * (select count(*) from events)")
def agg_heavy_hitters(s, d):
    return heavy_hitters(table(s, d, "events"), "user_id", 0.008)


_GEO = "region join nation on r_regionkey = n_regionkey join customer on c_nationkey = n_nationkey"


def _geo(s, d):
    return table(s, d, "region").join(table(s, d, "nation"), F.col("r_regionkey") == F.col("n_regionkey")).join(table(s, d, "customer"), F.col("c_nationkey") == F.col("n_nationkey"))


@query(f"select r_name, n_name, count(*) as n from {_GEO} group by rollup (r_name, n_name)")
def agg_rollup(s, d):
    return _geo(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query(f"select r_name, c_mktsegment, count(*) as n from {_GEO} group by cube (r_name, c_mktsegment)")
def agg_cube(s, d):
    return _geo(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query(f"select r_name, c_mktsegment, count(*) as n from {_GEO} group by grouping sets ((r_name), (c_mktsegment), ())")
def agg_grouping_sets(s, d):
    _geo(s, d).createOrReplaceTempView("toolkit_geo")
    return s.sql("select r_name, c_mktsegment, count(*) as n from toolkit_geo group by grouping sets ((r_name), (c_mktsegment), ())")


@query("select event_type, count(*) filter (value > 20) as high, sum(case when value <= 20 then 1 else 0 end)::bigint as low from events group by event_type")
def agg_conditional(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 20).alias("high"), F.sum(F.when(F.col("value") <= 20, 1).otherwise(0)).alias("low"))


@query(f"select src, max_by(dst, (p, -dst)) as best from (select src, dst, round(p, 9) as p from {_EDGES}) group by src".replace("max_by(dst, (p, -dst))", "arg_max(dst, row(p, -dst))"))
def agg_argmax(s, d):
    return net.net_events(s, d).groupBy("src").agg(F.max_by("dst", F.struct(F.round("p", 9), -F.col("dst"))).alias("best"))


@query(f"select src, string_agg(dst::varchar, ',' order by dst) as heads from {_EDGES} group by src")
def agg_nested(s, d):
    return net.net_events(s, d).groupBy("src").agg(F.array_join(F.array_sort(F.collect_list("dst")), ",").alias("heads"))


@query("select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view from events group by user_id")
def agg_pivot(s, d):
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count().na.fill(0)


@query(f"select src, dst, row_number() over w as rn, rank() over (partition by src order by round(p, 6) desc) as rk, dense_rank() over (partition by src order by round(p, 6) desc) as dr, ntile(4) over w as nt from {_EDGES} window w as (partition by src order by round(p, 6) desc, dst)")
def window_ranking(s, d):
    w, t = Window.partitionBy("src").orderBy(F.desc("p"), "dst"), Window.partitionBy("src").orderBy(F.desc("p"))
    e = net.net_events(s, d).withColumn("p", F.round("p", 6))
    return e.select("src", "dst", F.row_number().over(w).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as first_, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by ts, event_id)")
def window_analytic(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first_"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as day_count, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 4) as last3 from events")
def window_frames(s, d):
    table(s, d, "events").createOrReplaceTempView("toolkit_events")
    return s.sql("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as day_count, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 4) as last3 from toolkit_events")


@query(f"select src, dst from (select *, row_number() over (partition by src order by round(p, 9) desc, dst) as r from {_EDGES}) where r <= 3")
def top_k_per_group(s, d):
    return top_per_group(net.net_events(s, d), 3, ["src"], F.desc(F.round("p", 9)), F.col("dst")).select("src", "dst")


@query("select c_custkey from customer order by c_acctbal desc nulls last, c_custkey limit 10 offset 5")
def top_k_offset(s, d):
    return table(s, d, "customer").orderBy(F.desc_nulls_last("c_acctbal"), "c_custkey").offset(5).limit(10).select("c_custkey")


@query(f"select src as node from {_EDGES} union select dst from {_EDGES}")
def set_union(s, d):
    e = net.net_events(s, d)
    return e.select(F.col("src").alias("node")).union(e.select("dst")).distinct()


@query("select user_id from (select user_id from events where event_type = 'click' intersect all select user_id from events where event_type = 'view')")
def set_intersect_all(s, d):
    e = table(s, d, "events")
    return e.where("event_type = 'click'").select("user_id").intersectAll(e.where("event_type = 'view'").select("user_id"))


@query("select user_id from (select user_id from events where event_type = 'click' except all select user_id from events where event_type = 'view')")
def set_except_all(s, d):
    e = table(s, d, "events")
    return e.where("event_type = 'click'").select("user_id").exceptAll(e.where("event_type = 'view'").select("user_id"))


@query(f"with recursive t as ({sql.TREE_GEO}), r as (select 0::bigint as node, 0 as depth union all select t.node, r.depth + 1 from r join t on t.parent = r.node) select depth, count(*) as n from r group by depth")
def recursive_depths(s, d):
    net.tree_geography(s, d).createOrReplaceTempView("toolkit_tree")
    return s.sql("with recursive r(node, depth) as (select 0L, 0 union all select t.node, r.depth + 1 from r join toolkit_tree t on t.parent = r.node) select depth, count(*) as n from r group by depth")


@query("select c_custkey from customer c where c_acctbal > (select avg(c_acctbal) from customer x where x.c_nationkey = c.c_nationkey) and c_custkey in (select o_custkey from orders)")
def subqueries(s, d):
    for t in ("customer", "orders"):
        table(s, d, t).createOrReplaceTempView(f"toolkit_{t}")
    return s.sql("select c_custkey from toolkit_customer c where c_acctbal > (select avg(c_acctbal) from toolkit_customer x where x.c_nationkey = c.c_nationkey) and c_custkey in (select o_custkey from toolkit_orders)")


@query("select p_partkey, upper(split_part(p_name, ' ', 1)) as first_word, length(trim(p_name)) as n, substr(md5(p_name), 1, 8) as h, levenshtein(p_brand, 'Brand#11')::integer as far from part")
def functions_string(s, d):
    return table(s, d, "part").select("p_partkey", F.upper(F.split_part("p_name", F.lit(" "), F.lit(1))).alias("first_word"), F.length(F.trim("p_name")).cast("long").alias("n"), F.substring(F.md5("p_name"), 1, 8).alias("h"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("far"))


@query("select event_id, epoch_us(date_trunc('day', ts)) as day, date_diff('minute', date_trunc('day', ts), ts) as minutes, epoch_us(ts + interval 36 hour) as later from events")
def functions_date(s, d):
    day = F.date_trunc("day", "ts")
    return table(s, d, "events").select("event_id", micros(day).alias("day"), F.timestamp_diff("MINUTE", day, F.col("ts")).alias("minutes"), micros(F.col("ts") + F.make_dt_interval(hours=F.lit(36))).alias("later"))


@query("select event_id, round(pow(value, 2), 6) as sq, round(ln(1 + value), 6) as l, floor(value / 0.5) * 0.5 as grid, greatest(value, 10.0) as hi, ((event_id - 7) % 5 + 5) % 5 as m from events")
def functions_math(s, d):
    return table(s, d, "events").select("event_id", F.round(F.pow("value", F.lit(2)), 6).alias("sq"), F.round(F.log1p("value"), 6).alias("l"), (F.floor(F.col("value") / 0.5) * F.lit(0.5)).alias("grid"), F.greatest("value", F.lit(10.0)).alias("hi"), F.pmod(F.col("event_id") - 7, F.lit(5)).alias("m"))


@query("select user_id, len(t) as kinds, list_contains(t, 'error') as has_error, len(list_filter(t, lambda x: x > 'd')) as late, list_sum(list_transform(t, lambda x: length(x)))::bigint as letters from (select user_id, list_distinct(list(event_type)) as t from events group by user_id)")
def functions_array(s, d):
    t = F.array_distinct(F.collect_list("event_type"))
    return table(s, d, "events").groupBy("user_id").agg(t.alias("t")).select("user_id", F.size("t").cast("long").alias("kinds"), F.array_contains("t", "error").alias("has_error"), F.size(F.filter("t", lambda x: x > "d")).cast("long").alias("late"), F.aggregate("t", F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("letters"))


@query("select user_id, sum(n) filter (n > 15)::bigint as many from (select user_id, event_type, count(*) as n from events group by user_id, event_type) group by user_id having max(n) > 15".replace("filter (n > 15)::bigint", "filter (n > 15)"))
def functions_map(s, d):
    counts = table(s, d, "events").groupBy("user_id", "event_type").count()
    m = F.map_from_entries(F.collect_list(F.struct("event_type", "count")))
    high = counts.groupBy("user_id").agg(m.alias("m")).withColumn("m", F.map_filter("m", lambda k, v: v > 15)).where(F.size("m") > 0)
    return high.select("user_id", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("many"))


@query("select event_id, (props::json ->> '$.k')::integer as k from events")
def functions_json(s, d):
    return table(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query(f"select src, dst, {sql.coin(7, '0', 'src', 'dst')} as coin, floor(p * 4294967296)::bigint as live from {_EDGES}")
def functions_coin(s, d):
    return net.net_events(s, d).select("src", "dst", coin("portable", 7, F.lit(0), "src", "dst").alias("coin"), threshold("p").alias("live"))


@query("select vec_id, round(list_cosine_similarity(list_transform(embedding, lambda x: x::double), list_transform((select embedding from embeddings where vec_id = 0), lambda x: x::double)), 6) as cos from embeddings")
def functions_vector(s, d):
    v = table(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    first = v.where("vec_id = 0").select(F.col("v").alias("w"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda t, x: t + x)
    return v.crossJoin(F.broadcast(first)).select("vec_id", F.round(dot("v", "w") / F.sqrt(dot("v", "v") * dot("w", "w")), 6).alias("cos"))


@query(f"select src, dst, round(1 - pow(1 - p, 3), 6) as q, case when h < floor(p * 4294967296) then 'live' when h < floor((1 - pow(1 - p, 2)) * 4294967296) then 'raised' else 'blocked' end as state from (select *, {sql.coin(3, '5', 'src', 'dst')} as h from {_EDGES})")
def udf_sql(s, d):
    register(s)
    net.net_events(s, d).createOrReplaceTempView("toolkit_edges")
    return s.sql("select src, dst, round(boosted_prob(p, 3), 6) as q, coin_state(3, 5, src, dst, p, boosted_prob(p, 2)) as state from toolkit_edges")



@query(f"select range as sketch, {sql.coin(1, chr(39) + 'root' + chr(39), 'range')} % 150 as root from range(200)")
def udtf_sketch_roots(s, d):
    register(s)
    return s.sql("select * from sketch_roots(0, 200, 1, 150)")


@query(f"select range as world, 3::bigint as src, 8::bigint as dst, {sql.coin(1, 'range', '3', '8')} as coin from range(50)")
def udtf_world_coins(s, d):
    register(s)
    return s.sql("select * from world_coins(3, 8, 50, 1)")


@query("select p_partkey as node, (p_partkey - 1) // 2 as parent, p_name as name from part where p_partkey > 0")
def source_binary_tree(s, d):
    """A complete tree as large as the table of parts, with the parts' names."""
    register(s)
    part = table(s, d, "part").select(F.col("p_partkey").alias("node"), F.col("p_name").alias("name"))
    last = part.agg(F.max("node").alias("last")).first().last
    return s.read.format("binary_tree").option("nodes", (last or 0) + 1).load().join(part, "node")


@query("select true as activates_as_counted, true as marginals_as_counted")
def udf_arrow(s, d):
    x = Setting(s, d)
    k = x.sketches().where("category = 'boostable'")
    b = x.boost[:3]
    flags = k.select(sketch_activates(b)("root", "edges").alias("hit"), sketch_marginal_nodes(b)("root", "edges").alias("more"))
    return flags.agg((F.count_if(F.col("hit") & (F.size("more") > 0)) == 0).alias("activates_as_counted"), (F.count_if(~F.col("hit")) > 0).alias("marginals_as_counted"))


@query(f"select src, dst, round(p, 6) as p, round(1 - (1 - p) * (1 - p), 6) as q from {_EDGES}")
def source_edge_files(s, d):
    e = with_boost(net.net_events(s, d)).withColumns({c: F.round(c, 6) for c in ("p", "q")})
    last = None
    for fmt in ("parquet", "orc", "csv", "json"):
        path = scratch_path(s, f"edges-{fmt}")
        write_edges(e, path, fmt)
        if last is not None:  # no two formats but the one read and the one written lie side by side
            delete_path(s, last)
        e, last = read_edges(s, path, fmt), path
    return e


@query("select event_type as exp, case when event_type = 'click' then max(value) else min(value) end as value from events group by event_type")
def sink_run_log(s, d):
    """A log of each type's least value; the clicks come again with their largest and replace their own part only."""
    path = scratch_path(s, "runs")
    fixed = {"net": "events", "solver": "x", "seeds_mode": "random", "k": 1, "beta": 2.0, "eps": 0.5, "rep": 0, "measure": "value", "stderr": 0.0}
    by = table(s, d, "events").groupBy(F.col("event_type").alias("exp"))
    for value, exp in ((F.min("value"), None), (F.max("value"), "click")):
        runs = by.agg(value.alias("value")).withColumns({c: F.lit(v) for c, v in fixed.items()})
        append_runs(runs if exp is None else runs.where(F.col("exp") == exp), path)
    return s.read.parquet(path).select("exp", "value")


@query("""select src, dst, round(p, 9) as p, round(1 - (1 - p) * (1 - p), 9) as q
  from (select o_orderpriority[1]::bigint as src, ascii(o_orderstatus)::bigint as dst, count(*)::double / sum(count(*)) over (partition by o_orderpriority) as p from orders group by o_orderpriority, o_orderstatus)""")
def source_literal(s, d):
    """A small graph that the driver holds: from priorities to states, by the share of the priority's orders."""
    counts = table(s, d, "orders").groupBy("o_orderpriority", "o_orderstatus").count().collect()
    whole: dict = {}
    for r in counts:
        whole[r.o_orderpriority] = whole.get(r.o_orderpriority, 0) + r["count"]
    shares = [(r, r["count"] / whole[r.o_orderpriority]) for r in counts]
    return literal_graph(s, [(int(r.o_orderpriority[0]), ord(r.o_orderstatus), p, 1 - (1 - p) * (1 - p)) for r, p in shares]).withColumns({c: F.round(c, 9) for c in ("p", "q")})


@query(f"select src, dst from {_EDGES} where p > 0.05 and src between 3 and 90 and dst in (1, 2, 3, 5, 8, 13, 21, 34) and dst is not null")
def predicates(s, d):
    e = net.net_events(s, d)
    return e.where((F.col("p") > 0.05) & F.col("src").between(3, 90) & F.col("dst").isin(1, 2, 3, 5, 8, 13, 21, 34) & F.col("dst").isNotNull()).select("src", "dst")


@query("select true as same_rows, true as about_the_share")
def sample_by_hash(s, d):
    e = table(s, d, "events")
    a, b = net.hash_sample(e, 0.3, 5, "event_id").select("event_id"), net.hash_sample(e.orderBy("ts"), 0.3, 5, "event_id").select("event_id")
    return s.createDataFrame([(a.exceptAll(b).isEmpty(), abs(a.count() / e.count() - 0.3) < 0.1)], "same_rows boolean, about_the_share boolean")


@query(f"select dst, count(*) as n from {_EDGES} group by dst")
def clustered_edges(s, d):
    import uuid

    name = f"edges_{uuid.uuid4().hex[:10]}"
    save_clustered(net.net_events(s, d), name, "dst", 8)
    return s.table(name).groupBy("dst").agg(F.count("*").alias("n"))


@query(f"with recursive t as ({sql.FOREST}), r as (select distinct tree_id, 0::bigint as node, 0 as depth from t union all select t.tree_id, t.node, r.depth + 1 from r join t on t.tree_id = r.tree_id and t.parent = r.node) select depth::integer as depth, count(*) as n from r group by depth")
def udtf_tree_levels(s, d):
    register(s)
    net.forest_orders(s, d).createOrReplaceTempView("toolkit_forest")
    return s.sql("select depth, count(*) as n from tree_levels(table(toolkit_forest) partition by tree_id) group by depth")


@query("select count(*) as rows, count(*) filter (p > 0.1) as high from (" + sql.events() + ")")
def observed_metrics(s, d):
    """Counters that ride along with another job."""
    from pyspark.sql import Observation

    seen = Observation()
    net.net_events(s, d).observe(seen, F.count("*").alias("rows"), F.count_if(F.col("p") > 0.1).alias("high")).write.format("noop").mode("overwrite").save()
    got = seen.get
    return s.createDataFrame([(got["rows"], got["high"])], "rows long, high long")


@query(f"select src, dst, round(p, 6) as p from ({sql.events(6, 1.0)})")
def published_probabilities(s, d):
    """Snapshots of a stream merged by key; an epoch that comes twice changes nothing."""
    from nudgegraph.streaming import online

    held = {}

    def merge(rows, epoch):
        # the state is one row a pair of actor and action: it stays a table
        path = scratch_path(s, "published")
        old = held.get("first")
        new = rows if old is None else rows.unionByName(old)
        new.groupBy("actor", "action").agg(F.min("ts").alias("ts")).write.parquet(path)
        held["first"] = s.read.parquet(path)

    path = online.split_by_time(s, table(s, d, "events"), 2)
    online.publish(s, online.first_actions(online.stream_actions(s, path)), merge)
    first = held["first"]
    return online.probabilities(first, online.hits(first, first)).select("src", "dst", F.round("p", 6).alias("p"))
