"""Communities of every monthly snapshot, found by Louvain and followed from month to month.

Snapshots hold posts, topics and users, with edges between users where one answers another.

Louvain has no SQL, so these queries have none; tests compare them with brute force. The queries ``w39`` to
``w41`` follow given communities, which SQL can check.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from discourselab.operators import community
from discourselab.session import cut
from discourselab.sources import carriers as cv
from discourselab.workloads import Query, _snapshots, _tidied

#: The least number of users of a community, by group: the published floors' proportion.
FLOORS = {0: 6, 3: 3}
GAMMA = 0.01
BY = ("group_id",)


def communities(spark: SparkSession, d: str) -> DataFrame:
    """(group_id, period, community, user_id) of the focal groups in all months; the group leads a community's name."""
    out = None
    for group in cv.FOCAL:
        found = community.user_communities(community.louvain(_snapshots(spark, d, group, "month", *cv.PERIOD, replies=True)), FLOORS[group])
        part = found.select(F.lit(group).alias("group_id"), "period", F.concat_ws("|", F.lit(group), "community").alias("community"), "user_id")
        out = part if out is None else out.unionByName(part)
    return cut(out)


def w39c_louvain_links(spark: SparkSession, d: str) -> DataFrame:
    return community.evolve(communities(spark, d), 1, GAMMA, BY)


def w40c_louvain_evolution(spark: SparkSession, d: str) -> DataFrame:
    users = communities(spark, d)
    return community.classify_evolution(users, community.evolve(users, 1, GAMMA, BY), 1, BY)


def w40d_louvain_lifespans(spark: SparkSession, d: str) -> DataFrame:
    users = communities(spark, d)
    return community.lifespans(users, cut(community.evolve(users, 1, GAMMA, BY)), 1)


def w41b_louvain_sentiment(spark: SparkSession, d: str) -> DataFrame:
    scores = cv.posts_retail(spark, d).groupBy(F.col("author_id").alias("user_id")).agg(F.avg("sentiment").alias("mean_score"))
    return community.community_nodes(communities(spark, d), scores, BY)


def queries() -> dict[str, Query]:
    return {f.__name__: _tidied(f) for f in (w39c_louvain_links, w40c_louvain_evolution, w40d_louvain_lifespans, w41b_louvain_sentiment)}
