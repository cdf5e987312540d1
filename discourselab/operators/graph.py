"""Knowledge graph of posts, users, tags, incidents, dates, topics and groups as typed weighted triples."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RELATIONS = ("tweeted", "mentioned", "replied_to", "in_topic", "has_hashtag", "tweeted_on", "occurred_on", "victimized", "associated_with")


def node_id(kind: str, key: Column) -> Column:
    return F.concat(F.lit(f"{kind}:"), key.cast("string"))


def _edge(df: DataFrame, src: Column, dst: Column, rel: str, weight: Column | None = None) -> DataFrame:
    return df.select(src.alias("src"), dst.alias("dst"), F.lit(rel).alias("rel"), (F.lit(1.0) if weight is None else weight).alias("weight"))


def relevant_posts(members: DataFrame, groups: DataFrame, p_min: float = 0.01) -> DataFrame:
    """(post_id) of posts with a relevant topic."""
    return members.where(F.col("p") >= p_min).join(F.broadcast(groups.select("topic_id").distinct()), "topic_id", "left_semi").select("post_id").distinct()


def e_authored(posts: DataFrame) -> DataFrame:
    return _edge(posts, node_id("user", F.col("author_id")), node_id("post", F.col("post_id")), "tweeted")


def e_posted_on(posts: DataFrame) -> DataFrame:
    return _edge(posts, node_id("post", F.col("post_id")), node_id("date", F.col("day")), "tweeted_on")


def e_in_topic(members: DataFrame) -> DataFrame:
    return _edge(members, node_id("post", F.col("post_id")), node_id("topic", F.col("topic_id")), "in_topic", F.col("p"))


def e_tagged(tagged: DataFrame) -> DataFrame:
    """(post_id, tag) rows."""
    return _edge(tagged.distinct(), node_id("post", F.col("post_id")), node_id("hashtag", F.col("tag")), "has_hashtag")


def e_between_users(pairs: DataFrame, rel: str) -> DataFrame:
    """(src_user, dst_user) rows of replies or mentions; each pair once, weighted by how often."""
    counted = pairs.groupBy("src_user", "dst_user").agg(F.count("*").cast("double").alias("n"))
    return _edge(counted, node_id("user", F.col("src_user")), node_id("user", F.col("dst_user")), rel, F.col("n"))


def e_occurred_on(incidents: DataFrame) -> DataFrame:
    return _edge(incidents, node_id("incident", F.col("incident_id")), node_id("date", F.col("day")), "occurred_on")


def e_victimised(incidents: DataFrame) -> DataFrame:
    return _edge(incidents, node_id("incident", F.col("incident_id")), node_id("group", F.col("group_id")), "victimized")


def e_associated(groups: DataFrame) -> DataFrame:
    return _edge(groups, node_id("topic", F.col("topic_id")), node_id("group", F.col("group_id")), "associated_with")


def build_edges(
    posts: DataFrame,
    members: DataFrame,
    groups: DataFrame,
    incidents: DataFrame,
    tagged: DataFrame | None = None,
    replies: DataFrame | None = None,
    mentions: DataFrame | None = None,
    p_min: float = 0.01,
) -> DataFrame:
    """(src, dst, rel, weight) of all relations over the relevant posts."""
    kept = posts.join(relevant_posts(members, groups, p_min), "post_id", "left_semi")
    topics = (
        members.where(F.col("p") >= p_min)
        .join(F.broadcast(groups.select("topic_id").distinct()), "topic_id", "left_semi")
        .join(kept.select("post_id"), "post_id", "left_semi")
    )
    parts = [e_authored(kept), e_posted_on(kept), e_in_topic(topics), e_occurred_on(incidents), e_victimised(incidents), e_associated(groups)]
    if tagged is not None:
        parts.append(e_tagged(tagged.join(kept.select("post_id"), "post_id", "left_semi")))
    parts += [e_between_users(pairs, rel) for pairs, rel in ((replies, "replied_to"), (mentions, "mentioned")) if pairs is not None]
    return reduce(DataFrame.unionByName, parts)


def build_nodes(edges: DataFrame) -> DataFrame:
    """(node_id, kind) of every endpoint."""
    return edges.select(F.explode(F.array("src", "dst")).alias("node_id")).distinct().select("node_id", F.substring_index("node_id", ":", 1).alias("kind"))


def describe_nodes(nodes: DataFrame, facts: DataFrame) -> DataFrame:
    """(node_id, kind, key, props): nodes with the facts (node_id, name, value) known of them."""
    props = facts.groupBy("node_id").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("name", "value")))).alias("props"))
    none = F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<string>"))
    key = F.expr("substr(node_id, instr(node_id, ':') + 1)")
    return nodes.join(props, "node_id", "left").select("node_id", "kind", key.alias("key"), F.coalesce("props", none).alias("props"))


def node_facts(posts: DataFrame, incidents: DataFrame, groups: DataFrame) -> DataFrame:
    """(node_id, name, value): days of posts and incidents, posts of users, groups of topics."""
    fact = lambda df, node, name, value: df.select(node.alias("node_id"), F.lit(name).alias("name"), value.cast("string").alias("value"))
    users = posts.groupBy("author_id").agg(F.count("*").alias("n"))
    topics = groups.groupBy("topic_id").agg(F.count("*").alias("n"))
    parts = [
        fact(posts, node_id("post", F.col("post_id")), "day", F.col("day")),
        fact(posts, node_id("post", F.col("post_id")), "author", F.col("author_id")),
        fact(incidents, node_id("incident", F.col("incident_id")), "day", F.col("day")),
        fact(users, node_id("user", F.col("author_id")), "posts", F.col("n")),
        fact(topics, node_id("topic", F.col("topic_id")), "groups", F.col("n")),
    ]
    return reduce(DataFrame.unionByName, parts)


def with_day(edges: DataFrame) -> DataFrame:
    """Edges with the day of the post or incident at one of their ends; none for edges that have neither."""
    dated = (
        edges.where("rel in ('tweeted_on', 'occurred_on')")
        .select(F.col("src").alias("_at"), F.to_date(F.substring_index("dst", ":", -1)).alias("day"))
        .distinct()
    )
    end = F.when(F.col("rel") == "tweeted", F.col("dst")).otherwise(F.col("src"))
    keyed = edges.withColumn("_end", F.when(~F.col("rel").isin("associated_with", "replied_to", "mentioned"), end))
    return keyed.join(dated, F.col("_end") == F.col("_at"), "left").drop("_end", "_at")


def write_graph(edges: DataFrame, path: str) -> None:
    """Edges partitioned by relation, so that a subgraph reads its relations alone."""
    edges.write.mode("overwrite").partitionBy("rel").parquet(path)


def graph_stats(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(part, name, n) for each kind and relation, with totals (null names)."""
    one = lambda df, part, col: df.rollup(col).agg(F.count("*").alias("n")).select(F.lit(part).alias("part"), F.col(col).alias("name"), "n")
    return one(nodes, "node", "kind").unionByName(one(edges, "edge", "rel"))


def mean_topics(edges: DataFrame) -> DataFrame:
    """(mean_topics): memberships per post."""
    held = edges.where("rel in ('in_topic', 'tweeted')")
    n = lambda rel: F.sum(F.when(F.col("rel") == rel, 1).otherwise(0))
    return held.agg(F.try_divide(n("in_topic"), n("tweeted")).alias("mean_topics"))


def check_graph(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(check, violations): endpoints without a node, and counts that must agree."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node_id"))
    loose = ends.join(nodes, "node_id", "left_anti").agg(F.count("*").alias("violations")).select(F.lit("endpoints").alias("check"), "violations")
    count = lambda rel: F.sum(F.when(F.col("rel") == rel, 1).otherwise(0))
    pair = edges.agg(F.abs(count("tweeted") - count("tweeted_on")).alias("posts"), F.abs(count("occurred_on") - count("victimized")).alias("incidents"))
    return loose.unionByName(pair.unpivot([], ["posts", "incidents"], "check", "violations"))


def subgraph(edges: DataFrame, relations: tuple[str, ...], group: object | None = None, period: tuple[str, str] | None = None) -> DataFrame:
    """Edges of some relations; with a group, memberships in its topics and what touches their posts.

    With a period, edges that have a day (``with_day``) of it, both ends included, or none.
    """
    if period is not None:
        edges = edges.where(F.col("day").isNull() | F.col("day").between(*(F.lit(x).cast("date") for x in period)))
    kept = edges.where(F.col("rel").isin(*relations))
    if group is None:
        return kept
    topics = edges.where((F.col("rel") == "associated_with") & (F.col("dst") == node_id("group", F.lit(group)))).select(F.col("src").alias("topic"))
    posts = edges.where("rel = 'in_topic'").join(F.broadcast(topics), F.col("dst") == F.col("topic"), "left_semi").select(F.col("src").alias("post")).distinct()
    memberships = kept.where("rel = 'in_topic'").join(F.broadcast(topics), F.col("dst") == F.col("topic"), "left_semi")
    authored = kept.where("rel = 'tweeted'").join(posts, F.col("dst") == F.col("post"), "left_semi")
    dated = kept.where("rel in ('tweeted_on', 'has_hashtag')").join(posts, F.col("src") == F.col("post"), "left_semi")
    return memberships.unionByName(authored).unionByName(dated).unionByName(kept.where("rel not in ('in_topic', 'tweeted', 'tweeted_on', 'has_hashtag')"))


def date_bridge(edges: DataFrame) -> DataFrame:
    """(day, group, n_posts, n_incidents): posts and incidents of a group that share a date."""
    rel = lambda name: edges.where(F.col("rel") == name)
    topic_group = F.broadcast(rel("associated_with").select(F.col("src").alias("topic"), F.col("dst").alias("group")))
    posts = rel("in_topic").select(F.col("src").alias("post"), F.col("dst").alias("topic")).join(topic_group, "topic").select("post", "group").distinct()
    posts = (
        posts.join(rel("tweeted_on").select(F.col("src").alias("post"), F.col("dst").alias("day")), "post")
        .groupBy("day", "group")
        .agg(F.count("*").alias("n_posts"))
    )
    incidents = (
        rel("occurred_on")
        .select(F.col("src").alias("i"), F.col("dst").alias("day"))
        .join(rel("victimized").select(F.col("src").alias("i"), F.col("dst").alias("group")), "i")
        .groupBy("day", "group")
        .agg(F.count("*").alias("n_incidents"))
    )
    return posts.join(incidents, ["day", "group"])


def match_path(edges: DataFrame, relations: tuple[str, ...]) -> DataFrame:
    """(first, last, paths): how many directed paths through ``relations`` lead from a node to another.

    Counts are summed after every hop, so the table never holds the paths themselves.
    """
    hop = lambda rel: edges.where(F.col("rel") == rel).groupBy("src", "dst").agg(F.count("*").alias("k"))
    now = hop(relations[0]).select(F.col("src").alias("first"), F.col("dst").alias("last"), F.col("k").alias("paths"))
    for rel in relations[1:]:
        nxt = hop(rel)
        now = (
            now.join(nxt, F.col("last") == F.col("src"))
            .groupBy("first", "dst")
            .agg(F.sum(F.col("paths") * F.col("k")).alias("paths"))
            .withColumnRenamed("dst", "last")
        )
    return now


def cluster_profile(posts: DataFrame, members: DataFrame, users: DataFrame) -> DataFrame:
    """(topic_id, n_posts, mean_score): what a set of users writes about, and how."""
    kept = posts.join(users.select(F.col("user_id").alias("author_id")), "author_id", "left_semi")
    return kept.join(members, "post_id").groupBy("topic_id").agg(F.count_distinct("post_id").alias("n_posts"), F.avg("sentiment").alias("mean_score"))
