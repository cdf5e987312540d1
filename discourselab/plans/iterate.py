"""Loops over DataFrames: lineage is cut in shared storage, the driver sees one scalar a round."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from discourselab.session import cut


def until_stable(state: DataFrame, step: Callable[[DataFrame], DataFrame], fingerprint: Callable[[DataFrame], Row], max_rounds: int) -> DataFrame:
    """Apply ``step`` until ``fingerprint`` (a one-row summary) repeats; an error if it never does."""
    state = cut(state)
    before = fingerprint(state)
    for _ in range(max_rounds):
        state = cut(step(state))
        now = fingerprint(state)
        if now == before:
            return state
        before = now
    raise RuntimeError(f"not stable after {max_rounds} rounds")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, label) of every node of an undirected (src, dst) edge table; the label is the smallest node.

    Each round contracts towards the smallest neighbour, first among larger and then among smaller nodes;
    the rounds needed grow with the logarithm of a component's width.
    """

    def step(pairs: DataFrame) -> DataFrame:
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        wide = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        low = wide.groupBy("u").agg(F.min("v").alias("m"))
        return (
            wide.join(low, "u")
            .select(F.explode(F.array(F.struct("u", "m"), F.struct(F.col("v").alias("u"), "m"))).alias("e"))
            .select(F.col("e.u").alias("u"), F.col("e.m").alias("v"))
            .where("u > v")
            .distinct()
        )

    start = edges.select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).where("u > v").distinct()
    stars = until_stable(start, step, lambda d: d.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first(), max_rounds)
    nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    return nodes.join(stars, nodes.node == stars.u, "left").select("node", F.coalesce("v", "node").alias("label"))
