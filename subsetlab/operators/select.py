"""Exact top-n, top-q, median and rank kernels without a global sort or a task for each group, and the planner behind them.

A score's histogram (mergeable counts) locates the boundary bin; it is refined inside that bin until few rows remain.
Everything above the boundary passes a filter, and only boundary rows are sorted. Ties are broken by id. For groups the
same is done for all groups at once: each gets a cut, the last row that belongs to its winners, and rows are compared
with their group's cut where they are.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import stage

BINS = 4096


@dataclass(frozen=True)
class SelectionPlanner:
    """Up to sort_rows winners: Spark's bounded sort. Up to window_rows winners a group: ranked windows, where Spark limits groups early.

    boundary_rows may be sorted in one task; group_rows groups may be broadcast.
    """

    sort_rows: int = 100_000
    window_rows: int = 1000
    boundary_rows: int = 1_000_000
    group_rows: int = 1_000_000

    def global_kernel(self, n: int) -> str:
        return "sort" if n <= self.sort_rows else "histogram"

    def group_kernel(self, q: int) -> str:
        return "window" if q <= self.window_rows else "histogram"

    def small(self, groups: DataFrame) -> DataFrame:
        """A table with a row for each group: broadcast if it is that small, else merged."""
        return F.broadcast(groups) if groups.count() <= self.group_rows else groups.hint("merge")


DEFAULT = SelectionPlanner()


def _bin(score: str, lo, hi) -> Column:
    """0 .. BINS-1, larger for larger scores."""
    lo, hi = (x if isinstance(x, Column) else F.lit(x) for x in (lo, hi))
    width = (hi - lo) / F.lit(BINS)
    return F.coalesce(F.greatest(F.lit(0), F.least(F.lit(BINS - 1), F.floor(F.try_divide(F.col(score) - lo, width)))), F.lit(0)).cast("int")


def _usable(df: DataFrame, score: str) -> DataFrame:
    return df.filter(F.col(score).isNotNull() & ~F.isnan(F.col(score).cast("double")))


def top_n(df: DataFrame, n: int, score: str, id_: str, planner: SelectionPlanner = DEFAULT, ties: str | None = None) -> DataFrame:
    """The n rows of largest score; on ties the smaller value of ties (a number), then the smaller id, first.

    Null and NaN scores are never taken; n over the row count takes all.
    """
    df = _usable(df, score)
    order = [F.col(score).desc(), *([F.col(ties)] if ties else []), F.col(id_)]
    if n <= 0:
        return df.limit(0)
    if planner.global_kernel(n) == "sort":
        return df.orderBy(*order).limit(n)
    part, above, left = df, None, n
    while True:
        lo, hi, rows = part.agg(F.min(score), F.max(score), F.count(F.lit(1))).first()
        if rows <= left:
            return part if above is None else above.unionByName(part)
        if rows <= planner.boundary_rows or lo == hi or (hi - lo) / BINS + lo == lo:
            break
        counts = {r["b"]: r["n"] for r in part.groupBy(_bin(score, lo, hi).alias("b")).agg(F.count(F.lit(1)).alias("n")).collect()}  # BINS rows at most
        cut = max(counts)
        while counts[cut] <= left:
            left -= counts[cut]
            cut = max(b for b in counts if b < cut)
        over = part.filter(_bin(score, lo, hi) > cut)
        above = over if above is None else above.unionByName(over)
        part = part.filter(_bin(score, lo, hi) == cut)
        if left == 0:
            return above
    if lo == hi and rows > planner.boundary_rows:  # one score fills the boundary: go on by the next key
        chosen = top_n(part.withColumn("_next", -F.col(ties or id_)), left, "_next", id_, planner).drop("_next")
    else:
        chosen = part.orderBy(*order).limit(left)
    return chosen if above is None else above.unionByName(chosen)


def group_cuts(df: DataFrame, group: str, quota: int | DataFrame, score: str, id_: str, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(group, _cut, _cut_id): score and id of every group's quota-th row, by score from above and then by id.

    quota is a number or a table (group, quota). Groups with fewer rows than their quota, or a quota below 1, have no row here.
    Null and NaN scores do not count.
    """
    rows = _usable(df, score).select(group, F.col(score).alias("_s"), F.col(id_).alias("_i"))
    fixed = isinstance(quota, int)
    most = quota if fixed else (quota.agg(F.max("quota")).first()[0] or 0)
    order = Window.partitionBy(group).orderBy(F.col("_s").desc(), "_i")
    named = [group, F.col("_s").alias("_cut"), F.col("_i").alias("_cut_id")]
    if most < 1:
        return rows.limit(0).select(*named)
    if planner.group_kernel(most) == "window":
        ranked = rows.withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= most)
        return ranked.filter(F.col("_r") == most).select(*named) if fixed else ranked.join(planner.small(quota), group).filter(F.col("_r") == F.col("quota")).select(*named)
    rows = stage(df.sparkSession, rows, "scores")
    # lo and hi bound the scores among which the cut lies, left is its place there; one row for each group
    state = rows.groupBy(group).agg(F.min("_s").alias("lo"), F.max("_s").alias("hi"), F.count(F.lit(1)).alias("n"))
    state = state.withColumn("left", F.lit(most).cast("long")) if fixed else state.join(quota.select(group, F.col("quota").cast("long").alias("left")), group)
    state = stage(df.sparkSession, state.filter("left >= 1 AND left <= n"), "cuts")
    inside = lambda: rows.join(planner.small(state), group).filter(F.col("_s").between(F.col("lo"), F.col("hi")))
    by_id = False
    while True:
        wide = state.filter((F.col("n") > planner.boundary_rows) & (F.col("lo") < F.col("hi")))
        if wide.isEmpty():
            if by_id or state.filter(F.col("n") > planner.boundary_rows).isEmpty():
                break
            # one score fills a boundary: its rows go on by id
            tied = inside().select(group, F.when((F.col("n") > planner.boundary_rows), -F.col("_i").cast("double")).otherwise(F.col("_s").cast("double")).alias("_s"), "_i", F.col("_s").alias("_t"))
            rows, by_id = stage(df.sparkSession, tied, "scores"), True
            state = rows.groupBy(group).agg(F.min("_s").alias("lo"), F.max("_s").alias("hi"), F.count(F.lit(1)).alias("n")).join(state.select(group, "left"), group)
            state = stage(df.sparkSession, state, "cuts")
            continue
        bins = inside().groupBy(group, _bin("_s", F.col("lo"), F.col("hi")).alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min("_s").alias("lo"), F.max("_s").alias("hi"), F.max("left").alias("left"))
        upto = F.sum("n").over(Window.partitionBy(group).orderBy(F.col("b").desc()))  # BINS rows a group
        found = bins.withColumn("upto", upto).filter("upto >= left AND upto - n < left")
        narrow = stage(df.sparkSession, found.select(group, "lo", "hi", "n", (F.col("left") - F.col("upto") + F.col("n")).alias("left")), "cuts")
        if narrow.agg(F.sum("n")).first()[0] == state.agg(F.sum("n")).first()[0]:  # the scores are too close to be told apart
            state = narrow
            break
        state = narrow
    last = inside().withColumn("_r", F.row_number().over(order)).filter(F.col("_r") == F.col("left"))
    return last.select(group, F.col("_t" if by_id else "_s").alias("_cut"), F.col("_i").alias("_cut_id"))


def flag_top_q(df: DataFrame, group: str, q: int | DataFrame, score: str, id_: str, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """df plus the boolean picked: whether the row is among the q of largest score in its group; q is a number or a table (group, quota).

    Rows are compared with their group's cut in place: no window over whole groups. Rows without a group are not picked.
    """
    if isinstance(q, int) and q <= 0:
        return df.withColumn("picked", F.lit(False))
    cuts = stage(df.sparkSession, group_cuts(df, group, q, score, id_, planner), "cuts")
    allowed = F.lit(True)
    if not isinstance(q, int):
        df_ = df.join(planner.small(q.select(group, F.col("quota").alias("_quota"))), group, "left")
        allowed = F.coalesce(F.col("_quota") >= 1, F.lit(False))
    else:
        df_ = df
    s = F.col(score)
    within = F.col("_cut").isNull() | (s > F.col("_cut")) | ((s == F.col("_cut")) & (F.col(id_) <= F.col("_cut_id")))
    usable = s.isNotNull() & ~F.isnan(s.cast("double")) & F.col(group).isNotNull()
    return df_.join(planner.small(cuts), group, "left").withColumn("picked", F.coalesce(usable & allowed & within, F.lit(False))).select(*df.columns, "picked")


def top_q_per_group(df: DataFrame, group: str, q: int | DataFrame, score: str, id_: str, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """The q rows of largest score in each group; few winners a group by ranked windows that Spark limits early, else by cuts."""
    if isinstance(q, int) and planner.group_kernel(q) == "window":
        order = Window.partitionBy(group).orderBy(F.col(score).desc(), F.col(id_))
        return _usable(df, score).filter(F.col(group).isNotNull()).withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= q).drop("_r")
    return flag_top_q(df, group, q, score, id_, planner).filter("picked").drop("picked")


def rank_in_group(df: DataFrame, group: str, score: str, id_: str, name: str, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """df plus the row's rank in its group, by score from above and then by id; null scores come last. df should be a table.

    Up to sort_rows rows: one window. Beyond, rows are dealt by ranges of (group, score, id), and a rank is the number of the
    group's rows in earlier ranges plus the place within the range: large groups are spread over tasks, ties too.
    """
    order = [F.col(score).desc(), F.col(id_)]
    if df.count() <= planner.sort_rows:
        return df.withColumn(name, F.row_number().over(Window.partitionBy(group).orderBy(*order)))
    dealt = stage(df.sparkSession, df.repartitionByRange(F.col(group), *order).withColumn("_p", F.spark_partition_id()), "ranges")
    counts = dealt.groupBy(group, "_p").agg(F.count(F.lit(1)).alias("_n"))  # ranges and groups, added up
    before = Window.partitionBy(group).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(group, "_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    place = F.row_number().over(Window.partitionBy(group, "_p").orderBy(*order))
    ranked = dealt.withColumn("_place", place).join(planner.small(offsets), [group, "_p"])
    return ranked.withColumn(name, (F.col("_before") + F.col("_place")).cast("int")).select(*df.columns, name)


def group_median(df: DataFrame, group: str, value: str, id_: str, planner: SelectionPlanner = DEFAULT) -> DataFrame:
    """(group, median, n): the exact median of each group's values, nulls left out; the mean of the middle two for even counts."""
    rows = _usable(df, value)
    if rows.count() <= planner.sort_rows:
        return rows.groupBy(group).agg(F.percentile(value, 0.5).alias("median"), F.count(F.lit(1)).alias("n"))
    counts = stage(df.sparkSession, rows.groupBy(group).agg(F.count(F.lit(1)).alias("n")), "counts")
    upper, lower = (group_cuts(rows, group, counts.select(group, F.floor(at).cast("long").alias("quota")), value, id_, planner).select(group, F.col("_cut").alias(name)) for at, name in (((F.col("n") + 1) / 2, "_a"), (F.col("n") / 2 + 1, "_b")))
    return counts.join(upper, group).join(lower, group).select(group, ((F.col("_a") + F.col("_b")) / 2).alias("median"), "n")
