"""Measures of accuracy, agreement and cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def agreement(assigned: DataFrame, truth: DataFrame, key: str = "vec_id") -> DataFrame:
    """(purity, nmi, ari) of topic_id against label, from the contingency table alone."""
    cells = assigned.join(truth.select(key, "label"), key).groupBy("topic_id", "label").agg(F.count("*").alias("n"))
    rows, cols, every = Window.partitionBy("topic_id"), Window.partitionBy("label"), Window.partitionBy(F.lit(0))  # as many rows as cells
    held = cells.select(
        "n",
        F.sum("n").over(rows).alias("a"),
        F.sum("n").over(cols).alias("b"),
        F.sum("n").over(every).alias("t"),
        F.max("n").over(rows).alias("top"),
        F.row_number().over(rows.orderBy("label")).alias("ra"),
        F.row_number().over(cols.orderBy("topic_id")).alias("rb"),
    )
    pairs = lambda x: x * (x - 1) / 2.0
    once = lambda flag, x: F.sum(F.when(F.col(flag) == 1, x).otherwise(0.0))
    entropy = lambda c: -(F.col(c) / F.col("t")) * F.ln(F.col(c) / F.col("t"))
    s = held.agg(
        F.max("t").cast("double").alias("t"),
        once("ra", F.col("top")).alias("top"),
        F.sum((F.col("n") / F.col("t")) * F.ln(F.col("n") * F.col("t") / (F.col("a") * F.col("b")))).alias("mi"),
        once("ra", entropy("a")).alias("ha"),
        once("rb", entropy("b")).alias("hb"),
        F.sum(pairs(F.col("n"))).alias("ij"),
        once("ra", pairs(F.col("a"))).alias("i"),
        once("rb", pairs(F.col("b"))).alias("j"),
    )
    chance = F.col("i") * F.col("j") / pairs(F.col("t"))
    return s.select(
        (F.col("top") / F.col("t")).alias("purity"),
        F.try_divide("mi", F.sqrt(F.col("ha") * F.col("hb"))).alias("nmi"),
        F.try_divide(F.col("ij") - chance, (F.col("i") + F.col("j")) / 2 - chance).alias("ari"),
    )


def match_quality(matched: DataFrame, truth: DataFrame, by: str) -> DataFrame:
    """(by, tp, fp, fn, precision, recall, f1) of matched ids against a 0/1 column ``toxic``."""
    hit = truth.join(matched.select("doc_id").distinct().withColumn("hit", F.lit(1)), "doc_id", "left")
    n = lambda cond: F.sum(F.when(cond, 1).otherwise(0))
    found, bad = F.col("hit").isNotNull(), F.col("toxic") == 1
    counts = hit.groupBy(by).agg(n(found & bad).alias("tp"), n(found & ~bad).alias("fp"), n(~found & bad).alias("fn"))
    tp = F.col("tp")
    return counts.select(
        by,
        "tp",
        "fp",
        "fn",
        F.try_divide(tp, tp + F.col("fp")).alias("precision"),
        F.try_divide(tp, tp + F.col("fn")).alias("recall"),
        F.try_divide(2 * tp, 2 * tp + F.col("fp") + F.col("fn")).alias("f1"),
    )


def jaccard(a: DataFrame, b: DataFrame, on: str) -> DataFrame:
    """(jaccard) of two sets held as rows."""
    both = a.select(on).distinct().withColumn("x", F.lit(1)).join(b.select(on).distinct().withColumn("y", F.lit(1)), on, "full")
    return both.agg((F.sum(F.when(F.col("x").isNotNull() & F.col("y").isNotNull(), 1).otherwise(0)) / F.count("*")).alias("jaccard"))


def corpus_stats(posts: DataFrame, members: DataFrame) -> DataFrame:
    """(measure, n): posts, authors, days, memberships, topics."""
    p = posts.agg(F.count("*").alias("posts"), F.count_distinct("author_id").alias("authors"), F.count_distinct("day").alias("days"))
    m = members.agg(F.count("*").alias("memberships"), F.count_distinct("topic_id").alias("topics"))
    return p.crossJoin(m).unpivot([], ["posts", "authors", "days", "memberships", "topics"], "measure", "n")


def measure(run: Callable[[], DataFrame]) -> dict[str, float]:
    """Seconds, rows, stages, tasks and shuffled partitions of one run, from the status tracker."""
    begun = time.perf_counter()
    df = run()
    spark = df.sparkSession
    group = f"measure-{id(df)}"
    spark.sparkContext.setJobGroup(group, "measure")
    rows = df.count()
    tracker = spark.sparkContext.statusTracker()
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    stages = [tracker.getStageInfo(s) for j in jobs if j for s in j.stageIds]
    return {
        "seconds": time.perf_counter() - begun,
        "rows": float(rows),
        "jobs": float(len(jobs)),
        "stages": float(len(stages)),
        "tasks": float(sum(s.numTasks for s in stages if s)),
    }
