"""Selecting posts and incidents: period, place, terms, languages, categories."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from discourselab.functions.text import clean_text, runs_of

#: Terms that are broadcast; a longer list is joined by a shuffle.
BROADCAST_TERMS = 200_000


def clip_period(df: DataFrame, day: str, start: str, end: str) -> DataFrame:
    """Rows of the days from start to end, both included; the filter reaches the scan."""
    return df.where(F.col(day).between(F.lit(start).cast("date"), F.lit(end).cast("date")))


def clip_place(df: DataFrame, column: str, *places: object) -> DataFrame:
    return df.where(F.col(column).isin(*places))


def in_bbox(lat: Column, lon: Column, south: float, west: float, north: float, east: float) -> Column:
    """Inside a bounding box, which may cross the date line."""
    across = lon.between(west, east) if west <= east else (lon >= west) | (lon <= east)
    return lat.between(south, north) & across


def curate_terms(terms: DataFrame, stop_terms: DataFrame) -> DataFrame:
    return terms.join(stop_terms, "term", "left_anti")


def match_terms(posts: DataFrame, terms: DataFrame, key: str, text: str, mode: str = "token", keep_hyphen: bool = False) -> DataFrame:
    """(key, term) of the terms that occur in a post, each once.

    ``token`` explodes the word n-grams of the lengths that terms have and joins them by equality, so its
    cost follows the text and not the number of terms. ``regex`` (word boundaries) and ``substring`` try
    each term on each post: baselines for short lists.
    """
    held = terms.select(clean_text(F.col("term"), keep_hyphen).alias("term")).where("term <> ''").distinct()
    n = held.count()
    held = F.broadcast(held) if n <= BROADCAST_TERMS else held
    clean = posts.select(key, clean_text(F.col(text), keep_hyphen).alias("_clean"))
    if mode == "token":
        lengths = [r.k for r in held.select(F.size(F.split("term", " ")).alias("k")).distinct().collect()]
        grams = runs_of(F.split("_clean", " "), sorted(lengths) or [1])
        return clean.select(key, F.explode(grams).alias("term")).join(held, "term").select(key, "term").distinct()
    if mode == "regex":
        return (
            clean.join(held, F.regexp(F.concat(F.lit(" "), "_clean", F.lit(" ")), F.concat(F.lit(r"(?<=\s)\Q"), "term", F.lit(r"\E(?=\s)"))))
            .select(key, "term")
        )
    return clean.join(held, F.contains("_clean", "term")).select(key, "term")


def language_share(posts: DataFrame, stage: str) -> DataFrame:
    """(stage, lang, n, share)."""
    total = posts.agg(F.count("*").alias("total"))
    return (
        posts.groupBy("lang")
        .agg(F.count("*").alias("n"))
        .crossJoin(F.broadcast(total))
        .select(F.lit(stage).alias("stage"), "lang", "n", (F.col("n") / F.col("total")).alias("share"))
    )


def group_counts(scored: DataFrame, score: str) -> DataFrame:
    """(group_id, n_posts, n_negative, share) of (group_id, post_id, score) rows."""
    negative = F.sum(F.when(F.col(score) < 0, 1).otherwise(0))
    return scored.groupBy("group_id").agg(F.count("*").alias("n_posts"), negative.alias("n_negative"), (negative / F.count("*")).alias("share"))


def top_categories(incidents: DataFrame, column: str, k: int = 5) -> DataFrame:
    return incidents.groupBy(column).agg(F.count("*").alias("n")).orderBy(F.desc("n"), column).limit(k)


def rollup_motives(incidents: DataFrame) -> DataFrame:
    """(category, motive, n) with subtotals; nulls stand for all."""
    return incidents.rollup("category", "motive").agg(F.count("*").alias("n"))
