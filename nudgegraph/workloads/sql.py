"""SQL twins of the network builders, for an engine that checks ours."""

from __future__ import annotations

EVENT_ACTIONS = "select user_id as actor, event_type || '|' || props as action, min(ts) as ts from events group by user_id, event_type || '|' || props"
CUSTOMER_ACTIONS = "select o.o_custkey as actor, l.l_partkey as action, min(o.o_orderdate) as ts from lineitem l join orders o on l.l_orderkey = o.o_orderkey group by o.o_custkey, l.l_partkey"


def learned(actions: str, window: str, scale: float, ties: str = "") -> str:
    return f"""
  select h.src, h.dst, least(1.0::double, {float(scale)}::double * h.hits / d.done) as p
  from (select u.actor as src, v.actor as dst, count(*) as hits
        from ({actions}) u join ({actions}) v on u.action = v.action and u.actor <> v.actor and v.ts > u.ts and v.ts <= u.ts + interval '{window}'
        group by u.actor, v.actor) h
  join (select actor, count(*) as done from ({actions}) group by actor) d on d.actor = h.src {ties}"""


def events(hours: int = 6, scale: float = 4.0) -> str:
    return learned(EVENT_ACTIONS, f"{hours} hours", scale)


def customers(days: int = 365, scale: float = 4.0) -> str:
    ties = "join customer a on a.c_custkey = h.src join customer b on b.c_custkey = h.dst and a.c_nationkey = b.c_nationkey"
    return learned(CUSTOMER_ACTIONS, f"{days} days", scale, ties)


ORDER_SHARES = "select year(o_orderdate)::bigint as graph, " + ", ".join(f"avg((o_orderpriority = '{name}')::integer) as {at}" for at, name in zip("abcd", ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED"), strict=True)) + " from orders group by 1"


def raised_if(at: str, yes: bool) -> str:
    return f"(1 - (1 - {at}) * (1 - {at}))" if yes else at


def path_spread(b: tuple[int, ...]) -> str:
    one, two = raised_if("a", 1 in b), raised_if("b", 2 in b)
    return f"1 + {one} + {one} * {two}"


def star_spread(b: tuple[int, ...]) -> str:
    """Leaves 1 and 3 are seeds, the middle and leaf 2 are not."""
    middle = f"(1 - (1 - {raised_if('a', 0 in b)}) * (1 - {raised_if('c', 0 in b)}))"
    return f"2 + {middle} + {middle} * {raised_if('b', 2 in b)}"


def cover_spread(b: tuple[int, ...]) -> str:
    """Three sets with sure edges to their members: 4 is in the first, 5 and 6 in two, 7 in two, 8 and 9 in the third."""
    x, y, z = (raised_if(at, i + 1 in b) for i, at in enumerate("abc"))
    return f"1 + {x} + {y} + {z} + {x} + 2 * (1 - (1 - {x}) * (1 - {y})) + (1 - (1 - {y}) * (1 - {z})) + 2 * {z}"


def gate_spread(b: tuple[int, ...]) -> str:
    one = raised_if("a", 1 in b)
    two = f"(1 - (1 - {raised_if('c', 2 in b)}) * (1 - {one} * {raised_if('b', 2 in b)}))"
    return f"1 + {one} + {two} + {two} * {raised_if('d', 3 in b)}"


SUPPLIERS = """
  select src, dst, hits::double / sum(hits) over (partition by dst) as p
  from (select a.l_suppkey as src, b.l_suppkey as dst, count(*) as hits
        from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_suppkey <> b.l_suppkey and a.l_linenumber < b.l_linenumber
        group by a.l_suppkey, b.l_suppkey)"""

EMBEDDINGS = """
  select src, dst, least(1.0::double, greatest(cos, 0::double) * 0.15::double) as p
  from (select q.vec_id as src, c.vec_id as dst, c.cos, row_number() over (partition by q.vec_id order by c.cos desc, c.vec_id) as r
        from (select distinct vec_id from embeddings) q join (
          select x.vec_id as of_, y.vec_id, round(list_reduce(list_transform(list_zip(x.e, y.e), lambda z: z[1] * z[2]), lambda a, b: a + b) / (x.l * y.l), 9) as cos
          from (select vec_id, e, sqrt(list_reduce(list_transform(e, lambda x: x * x), lambda a, b: a + b)) as l from (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings)) x
          join (select vec_id, e, sqrt(list_reduce(list_transform(e, lambda x: x * x), lambda a, b: a + b)) as l from (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings)) y on x.vec_id <> y.vec_id
        ) c on c.of_ = q.vec_id)
  where r <= 10 and cos > 0"""

CONVERSATIONS = """
  select conv_id * 1000 + turn as src, conv_id * 1000 + next_ as dst, 100.0::double / (100 + n) as p
  from (select conv_id, turn, lead(turn) over (partition by conv_id order by turn) as next_, lead(length(text)) over (partition by conv_id order by turn) as n from conversations)
  where next_ is not null"""

PAGES = """
  select b.src, b.dst, b.n::double / s.n as p from (
    select x.id as src, y.id as dst, count(*) as n from own x join own y on x.word = y.word and x.id <> y.id group by x.id, y.id) b
  join (select id, count(*) as n from own group by id) s on s.id = b.src"""
PAGES_WITH = """own as (
  select distinct ('0x' || substr(md5(host), 1, 12))::bigint as id, word
  from (select regexp_extract(url, '://([^/:?#]+)', 1) as host, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) as word from pages) where host <> '')"""

TREE_PARTS = "select p_partkey as node, (p_partkey - 1) // 2 as parent from part where p_partkey > 0"
TREE_GEO = """
  select r_regionkey + 1 as node, 0::bigint as parent from region
  union all select n_nationkey + 100, n_regionkey + 1 from nation
  union all select c_custkey + 1000, c_nationkey + 100 from customer
  union all select s_suppkey + 1000000000, s_nationkey + 100 from supplier"""
FOREST = """
  select o_custkey as tree_id, (o_orderkey + 1) * 1000 as node, 0::bigint as parent from orders
  union all select o.o_custkey, (o.o_orderkey + 1) * 1000 + row_number() over (partition by l.l_orderkey order by l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate),
    (o.o_orderkey + 1) * 1000 from lineitem l join orders o on o.o_orderkey = l.l_orderkey"""


def coin(salt: int, *parts: str) -> str:
    """The portable coin."""
    text = " || '|' || ".join([f"'{salt}'", *[p if p.startswith("'") else f"({p})::varchar" for p in parts]])
    return f"('0x' || substr(md5({text}), 1, 8))::bigint"


def raised(edges: str) -> str:
    """p and q, and their thresholds."""
    return f"""select src, dst, p, 1 - (1 - p) * (1 - p) as q, floor(p * 4294967296)::bigint as tp, floor((1 - (1 - p) * (1 - p)) * 4294967296)::bigint as tq from ({edges})"""


def trivalent(pairs: str, salt: int = 7) -> str:
    """Both directions of (node, parent) with drawn chances."""
    c = coin(salt, "0", "src", "dst")
    return f"""select src, dst, [0.1::double, 0.01::double, 0.001::double][{c} % 3 + 1] as p from (
      select parent as src, node as dst from ({pairs}) union all select node, parent from ({pairs}))"""
