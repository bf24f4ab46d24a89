"""Networks and trees built from tables of actions, orders, vectors and turns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nudgegraph.functions.coins import coin
from nudgegraph.model import BoostGraph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


SECONDS = {"second": 1, "minute": 60, "hour": 3600, "day": 86_400, "week": 604_800}


def learn_probabilities(actions: DataFrame, ties: DataFrame | None, window: str, scale: float = 1.0, groups: DataFrame | None = None) -> DataFrame:
    """(src, dst, p): the share of src's actions that dst repeated within ``window``, such as ``6 hours``.

    ``actions``: (actor, action, ts), one row for each pair of actor and
    action; ``ties``: (src, dst) or None for all pairs; ``groups``: (actor,
    grp), only actors of one group meet. The self join is an equality on the
    action, the group and a slice of time a little wider than the window: a
    row meets its own slice and the next, so neither a popular action nor
    another group makes pairs that are thrown away. Counts are partially
    aggregated.
    """
    number, unit = window.split()
    width = int(number) * SECONDS[unit.rstrip("s")] + 86_400  # a day more than the window: a change of clocks moves no pair beyond reach
    done = actions.groupBy("actor").agg(F.count("*").alias("done"))
    own = actions.select("actor", "action", "ts").join(done, "actor")
    own = own.join(groups.select("actor", "grp"), "actor") if groups is not None else own.withColumn("grp", F.lit(0))
    own = own.withColumn("slice", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / width))
    u = own.select(F.col("actor").alias("src"), "done", "action", "grp", F.col("ts").alias("ts_u"), F.explode(F.array("slice", F.col("slice") + 1)).alias("slice"))
    v = own.select(F.col("actor").alias("dst"), "action", "grp", F.col("ts").alias("ts_v"), "slice")
    late = F.col("ts_u") + F.expr(f"interval {window}")
    met = u.join(v, ["action", "grp", "slice"]).where((F.col("src") != F.col("dst")) & (F.col("ts_v") > F.col("ts_u")) & (F.col("ts_v") <= late))
    hits = met.groupBy("src", "dst", "done").agg(F.count("*").alias("hits"))  # what src did comes along, so edges move once
    if ties is not None:
        hits = hits.join(ties.select("src", "dst").distinct(), ["src", "dst"], "left_semi")
    p = F.least(F.lit(1.0), F.lit(float(scale)) * F.col("hits") / F.col("done"))
    return hits.select("src", "dst", p.alias("p")).where("p > 0")


def customer_actions(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    bought = lines.select("l_orderkey", "l_partkey").join(orders.select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return bought.groupBy(F.col("o_custkey").alias("actor"), F.col("l_partkey").alias("action")).agg(F.min("o_orderdate").alias("ts"))


def net_customers(spark: SparkSession, sf_dir: str, days: int = 365, scale: float = 4.0) -> DataFrame:
    """Customers of one nation who bought the same part later."""
    nation = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("actor"), F.col("c_nationkey").alias("grp")).where("grp is not null")
    return learn_probabilities(customer_actions(spark, sf_dir), None, f"{days} days", scale, nation)


PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED")


def order_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(graph, p): by year of ordering the shares of orders with each of four priorities."""
    orders = table(spark, sf_dir, "orders")
    shares = [F.avg((F.col("o_orderpriority") == name).cast("double")) for name in PRIORITIES]
    return orders.groupBy(F.year("o_orderdate").cast("long").alias("graph")).agg(F.array(*shares).alias("p"))


def event_actions(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events").select("user_id", "event_type", "props", "ts")
    action = F.concat_ws("|", "event_type", "props")
    return events.groupBy(F.col("user_id").alias("actor"), action.alias("action")).agg(F.min("ts").alias("ts"))


def net_events(spark: SparkSession, sf_dir: str, hours: int = 6, scale: float = 4.0) -> DataFrame:
    """Users who did the same thing within some hours."""
    return learn_probabilities(event_actions(spark, sf_dir), None, f"{hours} hours", scale)


def event_networks(spark: SparkSession, sf_dir: str, *settings: tuple[int, float]) -> list[DataFrame] | list[BoostGraph]:
    """The networks of ``net_events`` by (hours, scale): tables, or graphs that find their edges from the actions where these are many."""
    from nudgegraph.sources.meetings import meeting_graphs

    found = meeting_graphs(event_actions(spark, sf_dir), [(f"{hours} hours", scale) for hours, scale in settings])
    return found or [net_events(spark, sf_dir, *s) for s in settings]


def events_graph(spark: SparkSession, sf_dir: str) -> BoostGraph:
    """The network of ``net_events`` as a graph that searches can start from."""
    from nudgegraph.sources.meetings import action_graph

    return action_graph(event_actions(spark, sf_dir), "6 hours", 4.0)


def net_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers of one order, from lower to higher line numbers; shares of all hits on the head."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_linenumber")
    a = line.toDF("order_", "src", "line_u")
    b = line.toDF("order_", "dst", "line_v")
    hits = a.join(b, "order_").where("src <> dst and line_u < line_v").groupBy("src", "dst").agg(F.count("*").alias("hits"))
    into = hits.groupBy("dst").agg(F.sum("hits").alias("into"))
    return hits.join(into, "dst").select("src", "dst", (F.col("hits") / F.col("into")).alias("p"))


def net_embeddings(spark: SparkSession, sf_dir: str, nearest: int = 10, scale: float = 0.15) -> DataFrame:
    """Each vector's nearest others by cosine; p is a share of the cosine.

    Blocks of rows meet blocks: every pair of blocks is one task, so no task
    holds more than two blocks.
    """
    import numpy as np
    import pandas as pd

    vectors = table(spark, sf_dir, "embeddings").select("vec_id", F.expr("transform(embedding, x -> cast(x as double))").alias("v"))
    blocks = max(1, -(-vectors.count() // 2048))
    own = vectors.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)))
    left = own.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = own.withColumnRenamed("b", "c").withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if a.empty or b.empty:
            return pd.DataFrame({"src": pd.Series(dtype="int64"), "dst": pd.Series(dtype="int64"), "cos": pd.Series(dtype="float64")})
        x, y = np.stack(a.v), np.stack(b.v)
        dot = np.zeros((len(x), len(y)))
        for j in range(x.shape[1]):
            dot += x[:, j : j + 1] * y[:, j]
        length = [np.sqrt(np.cumsum(z * z, 1)[:, -1]) for z in (x, y)]
        cos = np.round(dot / (length[0][:, None] * length[1]), 9)
        ids, other = a.vec_id.to_numpy(), b.vec_id.to_numpy()
        cos[ids[:, None] == other] = -np.inf
        rank = np.lexsort((np.broadcast_to(other, cos.shape), -cos))[:, :nearest]
        best = np.take_along_axis(cos, rank, 1)
        return pd.DataFrame({"src": np.repeat(ids, rank.shape[1]), "dst": other[rank].ravel(), "cos": best.ravel()})

    pairs = left.groupBy("b", "c").cogroup(right.groupBy("b", "c")).applyInPandas(near, "src long, dst long, cos double").where("cos > double('-infinity')")
    ranked = pairs.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst"))).where(f"r <= {nearest}")
    return ranked.select("src", "dst", F.least(F.lit(1.0), F.greatest(F.col("cos"), F.lit(0.0)) * F.lit(scale)).alias("p")).where("p > 0")


def net_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replies: from a turn to the next; p falls with the answer's length."""
    turn = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.length("text").alias("n"))
    after = Window.partitionBy("conv_id").orderBy("turn")
    step = turn.select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), (F.col("conv_id") * 1000 + F.lead("turn").over(after)).alias("dst"), F.lead("n").over(after).alias("n"))
    return step.where("dst is not null").select("src", "dst", (F.lit(100.0) / (100 + F.col("n"))).alias("p"))


def net_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts that link to the same words: p is the share of src's links that dst has too."""
    page = table(spark, sf_dir, "pages").select(F.regexp_extract("url", "://([^/:?#]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))).alias("word"))
    links = page.where("host <> ''").distinct()
    ids = links.select("host").distinct().withColumn("id", F.conv(F.substring(F.md5("host"), 1, 12), 16, 10).cast("long"))
    own = links.join(ids, "host").select("id", "word")
    both = own.toDF("src", "word").join(own.toDF("dst", "word"), "word").where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("both"))
    size = own.groupBy(F.col("id").alias("src")).agg(F.count("*").alias("size"))
    return both.join(size, "src").select("src", "dst", (F.col("both") / F.col("size")).alias("p"))


def two_way(child_parent: DataFrame) -> DataFrame:
    """(src, dst) in both directions of (node, parent)."""
    return child_parent.select(F.col("parent").alias("src"), F.col("node").alias("dst")).unionByName(child_parent.select(F.col("node").alias("src"), F.col("parent").alias("dst")))


def trivalency(edges: DataFrame, salt: int = 7, values: tuple[float, ...] = (0.1, 0.01, 0.001), mode: str = "portable") -> DataFrame:
    """p drawn from a few values by the edge's coin."""
    at = (coin(mode, salt, F.lit(0), "src", "dst") % len(values) + 1).cast("int")
    return edges.withColumn("p", F.element_at(F.array(*[F.lit(v) for v in values]), at))


def complete_binary_tree(spark: SparkSession, n: int) -> DataFrame:
    """(node, parent) of the tree on 0..n-1 in level order."""
    return spark.range(1, n).select(F.col("id").alias("node"), F.floor((F.col("id") - 1) / 2).cast("long").alias("parent"))


def tree_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").where("p_partkey > 0")
    return part.select(F.col("p_partkey").alias("node"), F.floor((F.col("p_partkey") - 1) / 2).cast("long").alias("parent"))


GEO_REGION, GEO_NATION, GEO_CUSTOMER, GEO_SUPPLIER = 1, 100, 1_000, 1_000_000_000


def tree_geography(spark: SparkSession, sf_dir: str) -> DataFrame:
    """World, regions, nations, and their customers and suppliers."""
    region = table(spark, sf_dir, "region").select((F.col("r_regionkey") + GEO_REGION).cast("long").alias("node"), F.lit(0).cast("long").alias("parent"))
    nation = table(spark, sf_dir, "nation").select((F.col("n_nationkey") + GEO_NATION).cast("long"), (F.col("n_regionkey") + GEO_REGION).cast("long"))
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey") + GEO_CUSTOMER, (F.col("c_nationkey") + GEO_NATION).cast("long"))
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_suppkey") + GEO_SUPPLIER, (F.col("s_nationkey") + GEO_NATION).cast("long"))
    return region.union(nation).union(customer).union(supplier)


def forest_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(tree_id, node, parent): a customer's orders and their lines.

    Order and line number don't name a line, so lines are numbered within
    their order by all columns that tell them apart.
    """
    orders = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("tree_id"), "o_orderkey")
    line = table(spark, sf_dir, "lineitem")
    order = Window.partitionBy("l_orderkey").orderBy(*[line[c] for c in line.columns if c != "l_orderkey"])
    line = line.withColumn("nth", F.row_number().over(order)).select("l_orderkey", "nth")
    first = orders.select("tree_id", ((F.col("o_orderkey") + 1) * 1000).alias("node"), F.lit(0).cast("long").alias("parent"))
    second = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("tree_id", ((F.col("o_orderkey") + 1) * 1000 + F.col("nth")).alias("node"), ((F.col("o_orderkey") + 1) * 1000).alias("parent"))
    return first.unionByName(second)


def check_graph(edges: DataFrame) -> DataFrame:
    """(fault, n): rows that break a rule, by rule; empty if all is well."""
    rules = [
        ("null id", "src is null or dst is null"),
        ("loop", "src = dst"),
        ("probability out of range", "p is null or q is null or isnan(p) or isnan(q) or p < 0 or q > 1"),
        ("raised below base", "q < p"),
    ]
    found = edges.select(F.explode(F.array(*[F.when(F.expr(rule), F.lit(name)) for name, rule in rules])).alias("fault")).where("fault is not null")
    twice = edges.groupBy("src", "dst").count().where("count > 1").select(F.lit("repeated edge").alias("fault"))
    return found.unionByName(twice).groupBy("fault").agg(F.count("*").alias("n"))


def merge_parallel(edges: DataFrame | list[BoostGraph], how: str = "max") -> DataFrame:
    """One edge a pair: the likeliest one, or the chance that any works.

    ``edges``: a table, or networks of actions (``sources.meetings``), whose
    parallel edges are merged where they are found.
    """
    from nudgegraph.operators.relational import noisy_or

    if isinstance(edges, list):
        from nudgegraph.sources.meetings import merged

        return merged(edges, how)
    made = {"max": F.max, "noisy_or": lambda c: noisy_or(F.col(c))}[how]
    return edges.groupBy("src", "dst").agg(made("p").alias("p"), made("q").alias("q"))


def hash_sample(df: DataFrame, share: float, salt: int, *ids: str) -> DataFrame:
    """The rows whose coin falls under the share: the same rows each time."""
    return df.where(coin("fast", salt, *ids) < int(share * (1 << 32)))
