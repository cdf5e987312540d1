"""Views that dress the given tables as posts, authors, incidents, memberships and links.

Every view is a lazy DataFrame with a fixed schema, so filters and column pruning reach the Parquet scan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from discourselab.session import table

MIN_P = 0.01
#: First and last day of the retail period, both included.
PERIOD = ("1995-01-01", "2001-08-01")
DEROGATORY = ("idiot", "moron", "clown", "scum", "worthless", "pathetic", "stupid", "trash", "loser", "disgusting")
#: The two groups whose behaviour is contrasted.
FOCAL = (0, 3)


def posts_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Microblog posts: events that carry a document's text, so texts recur like reposts."""
    docs = table(spark, sf_dir, "documents")
    n = docs.agg(F.count("*")).first()[0]
    events = table(spark, sf_dir, "events")
    texts = docs.select(F.col("doc_id"), F.col("text").alias("body"), "lang", "source")
    posts = events.select(
        F.col("event_id").alias("post_id"),
        F.col("user_id").alias("author_id"),
        F.col("ts").cast("timestamp").alias("posted_at"),
        F.to_date("ts").alias("day"),
        F.col("event_type").alias("kind"),
        F.pmod("event_id", F.lit(max(1, n))).alias("doc_id"),
    )
    return posts.join(texts, "doc_id")


def posts_retail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(post_id, author_id, day, month, sentiment) over eighty months."""
    x = 4 * (F.col("o_totalprice") - 250000) / 250000
    day = F.to_date("o_orderdate")
    return table(spark, sf_dir, "orders").select(
        F.col("o_orderkey").alias("post_id"),
        F.col("o_custkey").alias("author_id"),
        day.alias("day"),
        F.trunc(day, "month").alias("month"),
        (x / F.sqrt(x * x + 15)).alias("sentiment"),
    )


def profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, followers); followers are never negative."""
    return table(spark, sf_dir, "customer").select(
        F.col("c_custkey").alias("user_id"),
        F.greatest(F.lit(0), F.floor("c_acctbal")).cast("long").alias("followers"),
    )


def membership_retail(spark: SparkSession, sf_dir: str, min_p: float = MIN_P, posts: DataFrame | None = None) -> DataFrame:
    """(post_id, topic_id, p): share of each brand in an order's quantity, if at least ``min_p``.

    Lines are shuffled by post once, for the sums by topic and by post and for joins on the post.
    With ``posts``, only of those: their lines are picked first, and parts are shuffled to them, not broadcast.
    """
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    parts = table(spark, sf_dir, "part").select("p_partkey", F.substring("p_brand", 7, 3).cast("int").alias("topic_id"))
    if posts is not None:
        lines = lines.join(posts.select(F.col("post_id").alias("l_orderkey")), "l_orderkey", "left_semi")
        parts = parts.hint("merge")
    parts_of = (
        lines.join(parts, lines.l_partkey == parts.p_partkey)
        .select(F.col("l_orderkey").alias("post_id"), "topic_id", "l_quantity")
        .repartition("post_id")
        .groupBy("post_id", "topic_id")
        .agg(F.sum("l_quantity").alias("q"))
    )
    p = F.col("q") / F.sum("q").over(Window.partitionBy("post_id"))
    return parts_of.select("post_id", "topic_id", p.alias("p")).where(F.col("p") >= min_p)


def topic_groups(spark: SparkSession) -> DataFrame:
    """(topic_id, group_id): a many-to-many map of 23 topics; two topics are discarded."""
    topic = spark.range(1, 24).select(F.col("id").cast("int").alias("topic_id"))
    groups = F.when(F.col("topic_id") % 7 == 0, F.array(F.col("topic_id") % 5, (F.col("topic_id") + 1) % 5)).otherwise(F.array(F.col("topic_id") % 5))
    return topic.select("topic_id", F.explode(groups.cast("array<int>")).alias("group_id"))


def incidents_retail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(day, group_id, motive, category, offence, severity), one row per returned line."""
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_suppkey", "l_partkey", "l_shipdate", "l_quantity")
    nation = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    places = table(spark, sf_dir, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_regionkey", "n_name", "r_name")
    kinds = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    joined = lines.join(places, lines.l_suppkey == places.s_suppkey).join(kinds, lines.l_partkey == kinds.p_partkey)
    return joined.select(
        F.to_date("l_shipdate").alias("day"),
        F.col("n_regionkey").alias("group_id"),
        F.col("n_name").alias("motive"),
        F.col("r_name").alias("category"),
        F.col("p_type").alias("offence"),
        F.col("l_quantity").alias("severity"),
    )


def incidents_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(incident_id, occurred_at, day, group_id, motive) from error events."""
    errors = table(spark, sf_dir, "events").where("event_type = 'error'")
    return errors.select(
        F.col("event_id").alias("incident_id"),
        F.col("ts").cast("timestamp").alias("occurred_at"),
        F.to_date("ts").alias("day"),
        (F.col("user_id") % 5).cast("int").alias("group_id"),
        F.get_json_object("props", "$.k").cast("int").alias("motive"),
    )


def threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(post_id, author_id, reply_to) of conversation turns; each replies to the one before."""
    key = lambda turn: F.concat_ws(":", F.col("conv_id").cast("string"), turn.cast("string"))
    return table(spark, sf_dir, "conversations").select(
        key(F.col("turn")).alias("post_id"),
        F.concat_ws(":", F.col("conv_id").cast("string"), "role").alias("author_id"),
        F.when(F.col("turn") > 0, key(F.col("turn") - 1)).alias("reply_to"),
    )


def replies_stream(spark: SparkSession, sf_dir: str, within_seconds: int = 3600) -> DataFrame:
    """(src_user, dst_user, day, gap_seconds): an event answers the one before it with the same k.

    The order is by k and day, so no task sorts more than a day of one k; the first event of a day takes the
    last one of the day before.
    """
    events = table(spark, sf_dir, "events").select(
        "event_id",
        F.col("ts").cast("timestamp").alias("ts"),
        "user_id",
        F.get_json_object("props", "$.k").cast("int").alias("k"),
    )
    events = events.withColumn("day", F.to_date("ts"))
    order = Window.partitionBy("k", "day").orderBy("ts", "event_id")
    within = events.withColumn("dst_user", F.lag("user_id").over(order)).withColumn("before", F.lag("ts").over(order))
    last = events.groupBy("k", F.date_add("day", 1).alias("day")).agg(F.max_by(F.struct("user_id", "ts"), F.struct("ts", "event_id")).alias("last"))
    paired = within.join(last, ["k", "day"], "left")
    first = F.col("before").isNull()
    dst, before = F.when(first, F.col("last.user_id")).otherwise(F.col("dst_user")), F.when(first, F.col("last.ts")).otherwise(F.col("before"))
    gap = F.unix_micros("ts") - F.unix_micros(before)
    kept = paired.select(F.col("user_id").alias("src_user"), dst.alias("dst_user"), "day", gap.alias("gap"))
    near = kept.where((F.col("dst_user") != F.col("src_user")) & (F.col("gap") <= within_seconds * 1_000_000))
    return near.select("src_user", "dst_user", "day", F.floor(F.col("gap") / 1_000_000).cast("long").alias("gap_seconds"))


def replies_retail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(post_id, src_user, dst_user, day): an order answers the one before it of its day and priority."""
    order = Window.partitionBy("o_orderdate", "o_orderpriority").orderBy("o_orderkey")
    orders = table(spark, sf_dir, "orders").withColumn("_before", F.lag("o_custkey").over(order)).where("_before <> o_custkey")
    return orders.select(
        F.col("o_orderkey").alias("post_id"),
        F.col("o_custkey").alias("src_user"),
        F.col("_before").alias("dst_user"),
        F.to_date("o_orderdate").alias("day"),
    )


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, author, tags) of pages: the host, and the distinct targets of relative links."""
    tags = F.array_sort(F.array_distinct(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))))
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("author"), tags.alias("tags"))


def truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "labels").select("doc_id", "toxic", "quality")
