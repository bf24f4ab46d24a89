"""Relational operators around the methods: joins, aggregates and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from nudgegraph.plans.planner import salted_join

__all__ = ["asof_join", "heavy_hitters", "interval_join", "leave_one_out", "noisy_or", "range_join", "salted_join", "top_per_group"]


def noisy_or(p: Column) -> Column:
    """Aggregate: the chance that at least one of independent events happens; nulls don't count."""
    sure = F.max(F.coalesce((p >= 1).cast("int"), F.lit(0))) == 1
    return F.when(sure, 1.0).otherwise(F.coalesce(1 - F.exp(F.sum(F.when(p < 1, F.log1p(-p)))), F.lit(0.0)))


def leave_one_out(p: str, *keys: str) -> Column:
    """Window: the chance that at least one *other* event of the group happens, safe at chance one."""
    w = Window.partitionBy(*keys)
    x = F.col(p)
    one = (x >= 1).cast("int")
    others = F.sum(one).over(w) - one
    miss = F.sum(F.when(x < 1, F.log1p(-x)).otherwise(0.0)).over(w) - F.when(x < 1, F.log1p(-x)).otherwise(0.0)
    return F.when(others > 0, 1.0).otherwise(1 - F.exp(miss))


def range_join(left: DataFrame, right: DataFrame, on: list[str], left_ts: str, right_ts: str, width: float) -> DataFrame:
    """Pairs with equal keys and 0 < right_ts - left_ts <= width, by buckets of that width.

    A left row can only meet right rows of its own bucket or the next, so it
    is sent to both; equality on the bucket keeps the join a hash join.
    """
    a = left.withColumn("_b", F.explode(F.array(F.floor(F.col(left_ts) / width), F.floor(F.col(left_ts) / width) + 1)))
    b = right.withColumn("_b", F.floor(F.col(right_ts) / width))
    gap = F.col(right_ts) - F.col(left_ts)
    return a.join(b, [*on, "_b"]).where((gap > 0) & (gap <= width)).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, values: list[str], tolerance: float | None = None, slice_: float | None = None) -> DataFrame:
    """Each left row with the right row of its key that is last at or before its time.

    Both sides are put in one order by key and time and the last right row is
    carried on. With ``slice_`` (and a tolerance) a hot key's rows are dealt by
    time slices, right rows to their own and the following slices in reach.
    """
    a = left.withColumn("_side", F.lit(1)).withColumns({f"_r_{c}": F.lit(None).cast(right.schema[c].dataType) for c in values}).withColumn("_r_ts", F.lit(None).cast(right.schema[ts].dataType))
    own = {c for c in left.columns if c not in (by, ts)}
    b = right.select(by, ts, *[F.col(c).alias(f"_r_{c}") for c in values], F.col(ts).alias("_r_ts")).withColumn("_side", F.lit(0))
    for c in own:
        b = b.withColumn(c, F.lit(None).cast(left.schema[c].dataType))
    keys = [by]
    if slice_ is not None:
        reach = -(-int(tolerance) // int(slice_))
        a = a.withColumn("_s", F.floor(F.col(ts) / slice_))
        b = b.withColumn("_s", F.explode(F.sequence(F.floor(F.col(ts) / slice_), F.floor(F.col(ts) / slice_) + reach)))
        keys = [by, "_s"]
    w = Window.partitionBy(*keys).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b)
    carried = both.withColumns({f"_l_{c}": F.last(f"_r_{c}", True).over(w) for c in values} | {"_l_ts": F.last("_r_ts", True).over(w)}).where("_side = 1")
    near = F.lit(True) if tolerance is None else (F.col(ts) - F.col("_l_ts") <= tolerance)
    return carried.select(*left.columns, *[F.when(near, F.col(f"_l_{c}")).alias(f"{c}_asof") for c in values])


def interval_join(left: DataFrame, right: DataFrame, width: float, start: str = "since", end: str = "until") -> DataFrame:
    """Pairs of rows whose half-open intervals overlap; columns of right get the prefix ``r_``.

    An interval goes to every bucket it touches; a pair is given in the bucket
    in which its overlap starts, so it comes once.
    """
    spread = lambda df, s, e: df.withColumn("_b", F.explode(F.sequence(F.floor(F.col(s) / width), F.floor((F.col(e) - 1e-9) / width))))
    a = spread(left.where(F.col(start) < F.col(end)), start, end)
    renamed = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).where(F.col(f"r_{start}") < F.col(f"r_{end}"))
    b = spread(renamed, f"r_{start}", f"r_{end}")
    begins = F.greatest(F.col(start), F.col(f"r_{start}"))
    return a.join(b, "_b").where((F.col(start) < F.col(f"r_{end}")) & (F.col(f"r_{start}") < F.col(end)) & (F.floor(begins / width) == F.col("_b"))).drop("_b")


def top_per_group(df: DataFrame, k: int, group: list[str], *order: Column) -> DataFrame:
    """The first k rows of each group; partitions send no more than k of a group."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*group).orderBy(*order))).where(F.col("rank") <= k)


def heavy_hitters(df: DataFrame, key: str, share: float) -> DataFrame:
    """(key, n) of the keys that hold at least a share of all rows, exactly."""
    counts = df.groupBy(key).agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).where(F.col("n") >= share * F.col("total")).select(key, "n")
