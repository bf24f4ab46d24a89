"""URL filters with dated lists.

Dated entries of a list become validity intervals: an entry holds from its day
until the next entry for the same pattern. A capture is judged by the entries
that hold on the day it was fetched. Captures of one host and day are judged
once, so a host with a third of all captures costs a row a day.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nudgegraph.llm.text import need

HOST = r"^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)"


def host_of(url: str) -> F.Column:
    """Lower-case host; empty where there is none."""
    return F.coalesce(F.regexp_extract(F.lower(url), HOST, 1), F.lit(""))


def intervals(entries: DataFrame) -> DataFrame:
    """(pattern, wide, since, until): when each pattern is listed; until is exclusive and null while open.

    ``entries``: (pattern, wide, day, seq, listed). ``wide`` patterns match all
    hosts below them too. Of entries for one pattern on one day the one with
    the largest ``seq`` counts. Entries with a null pattern or day are void.
    """
    own = need(entries, "pattern", "wide", "day", "seq", "listed").where("pattern is not null and day is not null")
    last = own.groupBy("pattern", "wide", "day").agg(F.max_by("listed", F.coalesce("seq", F.lit(-1))).alias("listed"))
    until = F.lead("day").over(Window.partitionBy("pattern", "wide").orderBy("day"))
    return last.withColumn("until", until).where("listed").select("pattern", "wide", F.col("day").alias("since"), "until")


def filter_urls(captures: DataFrame, entries: DataFrame) -> DataFrame:
    """(page_id, host, fetched, blocked, n_entries, patterns) for every row of ``captures``.

    ``captures``: (page_id, url, fetched as a date). ``patterns`` has the
    patterns that hold, sorted and joined by commas. A url without a host, or
    null, and a null day match nothing. Rows may repeat and ids may be null:
    each row is judged by its url and day alone. Other columns are ignored.
    """
    own = need(captures, "page_id", "url", "fetched").select("page_id", host_of("url").alias("host"), "fetched")
    asked = own.where("host <> '' and fetched is not null").select("host", "fetched").distinct()
    parts = F.split("host", r"\.")
    keys = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))
    asked = asked.select("host", "fetched", F.explode(keys).alias("pattern"))
    held = intervals(entries)
    hit = asked.join(held, "pattern").where("fetched >= since and (until is null or fetched < until) and (wide or host = pattern)")
    judged = hit.groupBy("host", "fetched").agg(F.array_join(F.array_sort(F.collect_set("pattern")), ",").alias("patterns"), F.count_distinct("pattern").alias("n_entries"))
    out = own.join(judged, ["host", "fetched"], "left")
    return out.select("page_id", "host", "fetched", F.col("n_entries").isNotNull().alias("blocked"), F.coalesce("n_entries", F.lit(0)).cast("long").alias("n_entries"), F.coalesce("patterns", F.lit("")).alias("patterns"))


def _digest(column: str, word: str) -> F.Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(word + "|"), F.col(column))), 1, 8), 16, 10).cast("long")


def demo_captures(pages: DataFrame) -> DataFrame:
    """Pages with a day of fetching that their id gives."""
    day = F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("page_id", F.lit(365)).cast("int"))
    return need(pages, "page_id", "url").withColumn("fetched", day)


def demo_entries(pages: DataFrame) -> DataFrame:
    """A dated list over the pages' own hosts and their last two labels.

    The digest of a pattern says whether and when it is added, removed after
    60 days and added again after 120.
    """
    hosts = need(pages, "url").select(host_of("url").alias("host")).where("host <> ''").distinct()
    domain = F.substring_index("host", ".", -2)
    patterns = hosts.select(F.col("host").alias("pattern"), F.lit(False).alias("wide")).unionByName(hosts.select(domain.alias("pattern"), F.lit(True).alias("wide")).distinct())
    d = patterns.withColumn("h", F.when(F.col("wide"), _digest("pattern", "domain")).otherwise(_digest("pattern", "host")))
    start = F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("h", F.lit(300)).cast("int"))
    d = d.where("h % 3 = 0").withColumn("start", start)
    made = [("h % 3 = 0", 0, True, 0), ("h % 2 = 0", 60, False, 1), ("h % 5 = 0", 120, True, 2)]
    rows = [d.where(when).select("pattern", "wide", F.date_add("start", days).alias("day"), F.lit(seq).alias("seq"), F.lit(listed).alias("listed")) for when, days, listed, seq in made]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


ORACLE = r"""
with c as (
  select page_id, coalesce(regexp_extract(lower(url), '^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)', 1), '') as host,
         date '2024-01-01' + ((page_id % 365 + 365) % 365)::integer as fetched
  from pages
), h as (select distinct host from c where host <> ''),
pat as (
  select host as pattern, false as wide from h
  union select regexp_extract(host, '[^.]*(\.[^.]*)?$'), true from h
), d as (
  select *, ('0x' || substr(md5(case when wide then 'domain|' else 'host|' end || pattern), 1, 8))::bigint as x from pat
), s as (select *, date '2024-01-01' + (x % 300)::integer as start from d where x % 3 = 0),
e as (
  select pattern, wide, start as day, true as listed from s
  union all select pattern, wide, start + 60, false from s where x % 2 = 0
  union all select pattern, wide, start + 120, true from s where x % 5 = 0
), iv as (select *, lead(day) over (partition by pattern, wide order by day) as until from e),
hit as (
  select distinct c.host, c.fetched, iv.pattern
  from c join iv on iv.listed and (c.host = iv.pattern or (iv.wide and ends_with(c.host, '.' || iv.pattern)))
    and c.fetched >= iv.day and (iv.until is null or c.fetched < iv.until)
  where c.host <> ''
), j as (select host, fetched, count(*) as n, string_agg(pattern, ',' order by pattern) as p from hit group by host, fetched)
select c.page_id, c.host, c.fetched::varchar as fetched, j.n is not null as blocked, coalesce(j.n, 0)::bigint as n_entries, coalesce(j.p, '') as patterns
from c left join j on j.host = c.host and j.fetched = c.fetched
"""
