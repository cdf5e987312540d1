"""Daily series of posts and incidents, rolled, paired, ranked and compared."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from discourselab.functions.stats import p_column, spearman
from discourselab.functions.text import is_strong

MEASURES = ("n_posts", "mean_score", "strong_share")


def once_per_group(posts: DataFrame, members: DataFrame, groups: DataFrame) -> DataFrame:
    """Posts with group_id; a post counts once for a group however many of its topics it has."""
    pairs = members.join(F.broadcast(groups), "topic_id").select("post_id", "group_id").distinct()
    return posts.join(pairs, "post_id")


def daily_measures(grouped: DataFrame, score: str = "sentiment", tau: float = 0.5) -> DataFrame:
    """(group_id, day, n_posts, mean_score, strong_share, sum_score)."""
    strong = F.avg(is_strong(F.col(score), tau).cast("double"))
    return (
        grouped.groupBy("group_id", "day")
        .agg(F.count("*").alias("n_posts"), F.avg(score).alias("mean_score"), strong.alias("strong_share"), F.sum(score).alias("sum_score"))
    )


def daily_incidents(incidents: DataFrame) -> DataFrame:
    return incidents.groupBy("group_id", "day").agg(F.count("*").alias("n_incidents"))


def densify(series: DataFrame, start: str, end: str, counts: tuple[str, ...]) -> DataFrame:
    """A row for each group and day; missing counts are zero, missing means stay null."""
    days = F.sequence(F.lit(start).cast("date"), F.lit(end).cast("date"), F.expr("interval 1 day"))
    spine = series.select("group_id").distinct().select("group_id", F.explode(days).alias("day"))
    return spine.join(series, ["group_id", "day"], "left").fillna(0, list(counts))


def frame(days: int) -> Window:
    return Window.partitionBy("group_id").orderBy("day").rowsBetween(1 - days, 0)


def rolling(dense: DataFrame, columns: tuple[str, ...], days: int = 30, agg: str = "mean", min_periods: int = 5) -> DataFrame:
    """Trailing mean or sum over the last ``days`` rows of a dense series, once ``min_periods`` have passed."""
    window = frame(days)
    how = F.avg if agg == "mean" else F.sum
    enough = F.count("*").over(window) >= min_periods
    return dense.withColumns({c: F.when(enough, how(c).over(window)) for c in columns})


def rolling_by_range(series: DataFrame, column: str, days: int = 30) -> Column:
    """The same trailing mean on a sparse series, framed by day numbers instead of rows."""
    return F.avg(column).over(Window.partitionBy("group_id").orderBy(F.unix_date("day")).rangeBetween(1 - days, 0))


def pooled_mean(dense: DataFrame, days: int = 30) -> DataFrame:
    """Mean over all posts of the window, in place of the mean of daily means."""
    window = frame(days)
    return dense.withColumn("pooled", F.try_divide(F.sum("sum_score").over(window), F.sum("n_posts").over(window)))


def paired_series(posts: DataFrame, incidents: DataFrame, start: str, end: str, days: int = 30, min_periods: int = 5) -> DataFrame:
    """(group_id, day, r_posts, r_score, r_strong, r_incidents): the rolled twin-axis series."""
    p = rolling(densify(posts, start, end, ("n_posts",)), MEASURES, days, min_periods=min_periods)
    i = rolling(densify(incidents, start, end, ("n_incidents",)), ("n_incidents",), days, min_periods=min_periods)
    both = p.join(i, ["group_id", "day"], "left")
    return both.select(
        "group_id",
        "day",
        F.col("n_posts").alias("r_posts"),
        F.col("mean_score").alias("r_score"),
        F.col("strong_share").alias("r_strong"),
        F.col("n_incidents").alias("r_incidents"),
    )


def long_form(paired: DataFrame) -> DataFrame:
    """(group_id, day, measure, value, r_incidents), rounded so that equal values tie whatever the order of sums."""
    return (
        paired.unpivot(["group_id", "day", "r_incidents"], ["r_posts", "r_score", "r_strong"], "measure", "value")
        .withColumns({c: F.round(c, 9) for c in ("value", "r_incidents")})
    )


def correlation_table(paired: DataFrame) -> DataFrame:
    """(group_id, measure, n, r_s): every measure against incidents."""
    return spearman(long_form(paired), "value", "r_incidents", ["group_id", "measure"])


def with_p(correlations: DataFrame) -> DataFrame:
    return correlations.withColumn("p", p_column(F.col("r_s"), F.col("n")))


def lagged_spearman(paired: DataFrame, lags: list[int]) -> DataFrame:
    """(group_id, measure, lag, n, r_s): incidents ``lag`` days after the measure, ranked on the overlap."""
    long = long_form(paired)
    grid = long.sparkSession.createDataFrame([(k,) for k in lags], "lag int")
    left = long.select("group_id", "measure", "day", "value").crossJoin(F.broadcast(grid)).withColumn("at", F.date_add("day", F.col("lag")))
    right = paired.select("group_id", F.col("day").alias("at"), "r_incidents")
    return spearman(left.join(right, ["group_id", "at"]), "value", "r_incidents", ["group_id", "measure", "lag"])


def cross_group_corr(paired: DataFrame, a: int, b: int) -> DataFrame:
    """Does a measure run against itself in another group? (measure, n, r_s)."""
    long = long_form(paired)
    one, two = (long.where(F.col("group_id") == g).select("measure", "day", F.col("value").alias(name)) for g, name in ((a, "x"), (b, "y")))
    return spearman(one.join(two, ["measure", "day"]), "x", "y", ["measure"])


def peaks(long: DataFrame) -> DataFrame:
    """(group_id, measure, peak_day, peak_value): the first day of each series' maximum."""
    held = long.where("value is not null")
    return (
        held.groupBy("group_id", "measure")
        .agg(F.max(F.struct("value", (-F.unix_date("day")).alias("d"))).alias("m"))
        .select("group_id", "measure", F.date_from_unix_date(-F.col("m.d")).alias("peak_day"), F.col("m.value").alias("peak_value"))
    )


def series_summary(long: DataFrame) -> DataFrame:
    low, high = F.min("value"), F.max("value")
    return (
        long.where("value is not null")
        .groupBy("group_id", "measure")
        .agg(low.alias("low"), F.avg("value").alias("mean"), high.alias("high"), (high - low).alias("span"))
    )


def decay(long: DataFrame, frac: float = 0.5) -> DataFrame:
    """(group_id, measure, days_to_fall): days from the peak until the series is under ``frac`` of it."""
    top = peaks(long)
    under = long.join(top, ["group_id", "measure"]).where((F.col("day") > F.col("peak_day")) & (F.col("value") < F.col("peak_value") * frac))
    first = under.groupBy("group_id", "measure").agg(F.min(F.datediff("day", "peak_day")).alias("days_to_fall"))
    return top.select("group_id", "measure").join(first, ["group_id", "measure"], "left")


def event_window(long: DataFrame, calendar: DataFrame, k: int = 30) -> DataFrame:
    """(group_id, measure, event_day, before, after): means over k days before and after dated events."""
    near = long.join(F.broadcast(calendar), "group_id").where((F.datediff("day", "event_day") >= -k) & (F.datediff("day", "event_day") <= k))
    side = lambda cond: F.avg(F.when(cond, F.col("value")))
    return (
        near.groupBy("group_id", "measure", "event_day")
        .agg(side(F.col("day") < F.col("event_day")).alias("before"), side(F.col("day") > F.col("event_day")).alias("after"))
    )


def annotate_events(weekly: DataFrame, calendar: DataFrame) -> DataFrame:
    """Marks the weeks that hold a known event of the group."""
    days = F.broadcast(calendar.select(F.col("group_id").alias("_g"), F.to_date(F.date_trunc("week", "event_day")).alias("_week")).distinct())
    return (
        weekly.join(days, (F.col("group_id") == F.col("_g")) & (F.col("week") == F.col("_week")), "left")
        .withColumn("has_event", F.col("_g").isNotNull())
        .drop("_g", "_week")
    )
