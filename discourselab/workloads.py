"""The experiment workloads on the given tables, as registered queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from discourselab import oracles
from discourselab.functions import text as tx
from discourselab.functions.stats import pearson
from discourselab.operators import community, general, graph, influence, measures, select, series, topics
from discourselab.session import prepare, scratch, settle, table
from discourselab.sources import carriers as cv
from discourselab.streaming import monitor

Query = Callable[[SparkSession, str], DataFrame]

BASE_TERMS = ("idiot", "worthless clown", "black box", "city", "box of lies", "match", "toy", "press")
#: An invented calendar: three dates for each group.
CALENDAR = [(g, f"{1996 + k}-{3 + g:02d}-15") for g in range(5) for k in range(3)]
EIGEN_STEPS = 15


def tidy(df: DataFrame) -> DataFrame:
    """Doubles rounded to six places, without negative zeros."""
    return df.select(*((F.round(c, 6) + 0.0).alias(c) if kind == "double" else F.col(c) for c, kind in df.dtypes))


def _calendar(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CALENDAR, "group_id int, d string").select("group_id", F.to_date("d").alias("event_day"))


def _phrases(spark: SparkSession, d: str) -> DataFrame:
    words = F.split(tx.clean_text(F.col("text")), " ")
    held = table(spark, d, "benchmark").where(F.size(words) >= 4).select(F.array_join(F.slice(words, 1, 4), " ").alias("term"))
    ten = spark.createDataFrame([(w,) for w in cv.DEROGATORY], "term string")
    return ten.unionByName(held).distinct()


def _grouped(spark: SparkSession, d: str) -> DataFrame:
    return series.once_per_group(cv.posts_retail(spark, d), cv.membership_retail(spark, d), cv.topic_groups(spark))


def _paired(spark: SparkSession, d: str) -> DataFrame:
    return series.paired_series(series.daily_measures(_grouped(spark, d)), series.daily_incidents(cv.incidents_retail(spark, d)), *cv.PERIOD)


def _focal(df: DataFrame) -> DataFrame:
    return df.where(F.col("group_id").isin(*cv.FOCAL))


# texts


def w01_clean_text(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", F.md5(tx.clean_text(F.col("text"))).alias("clean_hash"))


def w02_expand_terms(spark: SparkSession, d: str) -> DataFrame:
    return tx.expand_terms(spark.createDataFrame([(t,) for t in BASE_TERMS], "base string"))


def _matched_docs(spark: SparkSession, d: str) -> DataFrame:
    """Matched terms of each document; posts that reuse a text share its matches."""
    return select.match_terms(table(spark, d, "documents").select("doc_id", "text"), _phrases(spark, d), "doc_id", "text")


def _posts_of(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "documents").agg(F.count("*")).first()[0]
    return table(spark, d, "events").select(F.col("event_id").alias("post_id"), F.pmod("event_id", F.lit(n)).alias("doc_id"))


def w03_term_filter(spark: SparkSession, d: str) -> DataFrame:
    terms = _matched_docs(spark, d).groupBy("doc_id").agg(F.array_sort(F.collect_set("term")).alias("t"))
    return _posts_of(spark, d).join(terms, "doc_id").select("post_id", F.size("t").cast("long").alias("n_terms"), F.array_join("t", ",").alias("terms"))


def w04_term_filter_phrases(spark: SparkSession, d: str) -> DataFrame:
    phrases = _phrases(spark, d).where(F.contains("term", F.lit(" "))).withColumnRenamed("term", "base")
    expanded = tx.expand_terms(phrases, plurals=False).select("term")
    return select.match_terms(table(spark, d, "documents"), expanded, "doc_id", "text", keep_hyphen=True).select("doc_id", F.col("term").alias("phrase"))


def w04b_curated_terms(spark: SparkSession, d: str) -> DataFrame:
    """Matches of the list without its generic terms."""
    stop = spark.createDataFrame([(w,) for w in cv.DEROGATORY], "term string")
    return select.match_terms(table(spark, d, "documents"), select.curate_terms(_phrases(spark, d), stop), "doc_id", "text")


def w05_language_share(spark: SparkSession, d: str) -> DataFrame:
    posts = _posts_of(spark, d).join(table(spark, d, "documents").select("doc_id", "lang"), "doc_id")
    kept = posts.join(_matched_docs(spark, d).select("doc_id"), "doc_id", "left_semi")
    return select.language_share(posts, "before").unionByName(select.language_share(kept, "after"))


def w06_group_negative_stats(spark: SparkSession, d: str) -> DataFrame:
    return select.group_counts(_grouped(spark, d), "sentiment")


def _clipped(spark: SparkSession, d: str) -> DataFrame:
    return select.clip_period(cv.incidents_retail(spark, d), "day", *cv.PERIOD)


def w07_top_motives(spark: SparkSession, d: str) -> DataFrame:
    return select.top_categories(_clipped(spark, d), "motive")


def w07b_place_motives(spark: SparkSession, d: str) -> DataFrame:
    """The most frequent motives of one region."""
    return select.top_categories(select.clip_place(_clipped(spark, d), "category", "EUROPE", "ASIA"), "motive")


def w07c_bounding_box(spark: SparkSession, d: str) -> DataFrame:
    """Nations in a box across the date line, at invented places."""
    key = F.col("n_nationkey")
    places = table(spark, d, "nation").select(key, (key * 37 % 181 - 90).alias("lat"), (key * 53 % 361 - 180).alias("lon"))
    return places.where(select.in_bbox(F.col("lat"), F.col("lon"), -60, 100, 60, -100)).select("n_nationkey")


def w08_top_offences(spark: SparkSession, d: str) -> DataFrame:
    return select.top_categories(_clipped(spark, d), "offence")


def w08b_motive_rollup(spark: SparkSession, d: str) -> DataFrame:
    return select.rollup_motives(_clipped(spark, d))


def _scored(spark: SparkSession, d: str, rules: tx.Rules | None) -> DataFrame:
    docs = table(spark, d, "documents").select("doc_id", tx.sentiment(F.col("text"), rules=rules).alias("score"))
    return _posts_of(spark, d).join(docs, "doc_id").select("post_id", "score")


def w09_sentiment_rules(spark: SparkSession, d: str) -> DataFrame:
    return _scored(spark, d, tx.Rules())


def w10_sentiment_plain(spark: SparkSession, d: str) -> DataFrame:
    return _scored(spark, d, None)


def w09b_sentiment_clean(spark: SparkSession, d: str) -> DataFrame:
    """Scores of cleaned texts, which have lost what some rules read."""
    docs = table(spark, d, "documents").select("doc_id", tx.sentiment(F.col("text"), rules=tx.Rules(), text_form="clean").alias("score"))
    return _posts_of(spark, d).join(docs, "doc_id").select("post_id", "score")


def w10c_sentiment_arrow(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").select("doc_id", tx.sentiment_arrow(F.col("text")).alias("score"))
    return _posts_of(spark, d).join(docs, "doc_id").select("post_id", "score")


def w10d_posts_text(spark: SparkSession, d: str) -> DataFrame:
    """Microblog posts by day and language."""
    return cv.posts_text(spark, d).groupBy("day", "lang").agg(F.count("*").alias("n"), F.sum(F.length("body")).alias("chars"))


def w10b_polarity(spark: SparkSession, d: str) -> DataFrame:
    return cv.posts_retail(spark, d).groupBy(tx.polarity(F.col("sentiment")).alias("polarity")).agg(F.count("*").alias("n"))


def w11_strong_share(spark: SparkSession, d: str) -> DataFrame:
    strong = F.avg(tx.is_strong(F.col("sentiment")).cast("double"))
    return _grouped(spark, d).groupBy("group_id").agg(F.count("*").alias("n"), strong.alias("strong_share"))


# topics


def _members_text(spark: SparkSession, d: str) -> DataFrame:
    vectors = table(spark, d, "embeddings")
    return topics.soft_membership(vectors, topics.centers(vectors))


def w12_soft_membership(spark: SparkSession, d: str) -> DataFrame:
    return _members_text(spark, d).where(F.col("p") >= cv.MIN_P)


def w13_hard_assign(spark: SparkSession, d: str) -> DataFrame:
    return topics.hard_assign(_members_text(spark, d))


def w14_rescue(spark: SparkSession, d: str) -> DataFrame:
    return topics.rescue_outliers(_members_text(spark, d), cut_p=0.6)


def _labelled_texts(spark: SparkSession, d: str) -> DataFrame:
    labels = table(spark, d, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("label").alias("topic_id"))
    return table(spark, d, "documents").select("doc_id", "text").join(labels, "doc_id").select("topic_id", "text")


def w15_class_tfidf(spark: SparkSession, d: str) -> DataFrame:
    return topics.top_terms(topics.class_tfidf(_labelled_texts(spark, d)), 50).select("topic_id", "term", "weight")


def w16_topic_names(spark: SparkSession, d: str) -> DataFrame:
    return topics.name_topics(topics.class_tfidf(_labelled_texts(spark, d)))


def w17_topic_summary(spark: SparkSession, d: str) -> DataFrame:
    return topics.topic_summary(cv.membership_retail(spark, d), "post_id")


def w17b_noise_topics(spark: SparkSession, d: str) -> DataFrame:
    return topics.flag_noise_topics(_labelled_texts(spark, d), 0.02)


def w18_group_summary(spark: SparkSession, d: str) -> DataFrame:
    return topics.group_summary(cv.membership_retail(spark, d), cv.topic_groups(spark))


def w19_weekly_share_topic(spark: SparkSession, d: str) -> DataFrame:
    return topics.weekly_share(cv.membership_retail(spark, d), cv.posts_retail(spark, d), "topic")


def w20_weekly_share_week(spark: SparkSession, d: str) -> DataFrame:
    return topics.weekly_share(cv.membership_retail(spark, d), cv.posts_retail(spark, d), "week")


def w20b_heatmap_topics(spark: SparkSession, d: str) -> DataFrame:
    picked = topics.pick_topics(cv.topic_groups(spark))
    return w19_weekly_share_topic(spark, d).join(F.broadcast(picked), "topic_id").select("group_id", "topic_id", "week", "n", "share")


def w20c_annotated_weeks(spark: SparkSession, d: str) -> DataFrame:
    return series.annotate_events(w20b_heatmap_topics(spark, d), _calendar(spark)).select("group_id", "topic_id", "week", "has_event")


def w52_density_clusters(spark: SparkSession, d: str) -> DataFrame:
    """Agreement with the labels of density and centroid clustering on planted and on raw vectors."""
    raw = table(spark, d, "embeddings")
    planted = topics.plant(raw, "label", 2.5)
    rows = [
        ("planted", "density", topics.cluster_density(planted, 20), planted),
        ("planted", "centroid", topics.cluster_centroid(planted, 10, 20), planted),
        ("planted", "random", topics.random_topics(planted, 10), planted),
        ("raw", "density", topics.cluster_density(raw, 20), raw),
    ]
    parts = [measures.agreement(found, truth.select("vec_id", "label")).select(F.lit(data).alias("data"), F.lit(how).alias("method"), "purity", "nmi", "ari") for data, how, found, truth in rows]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


# series


def w21_daily_measures(spark: SparkSession, d: str) -> DataFrame:
    return series.daily_measures(_grouped(spark, d)).drop("sum_score")


def w22_rolling_counts(spark: SparkSession, d: str) -> DataFrame:
    return _focal(_paired(spark, d)).select("group_id", "day", "r_posts", "r_incidents")


def w23_rolling_sentiment(spark: SparkSession, d: str) -> DataFrame:
    return _focal(_paired(spark, d)).select("group_id", "day", "r_score", "r_incidents")


def w24_rolling_strong(spark: SparkSession, d: str) -> DataFrame:
    return _focal(_paired(spark, d)).select("group_id", "day", "r_strong", "r_incidents")


def w24b_pooled_mean(spark: SparkSession, d: str) -> DataFrame:
    daily = series.daily_measures(_grouped(spark, d))
    return series.pooled_mean(series.densify(daily, *cv.PERIOD, ("n_posts", "sum_score"))).select("group_id", "day", "pooled")


def w24c_rolling_week_stream(spark: SparkSession, d: str) -> DataFrame:
    """Seven-day rolled incidents of the event stream's month, by group."""
    daily = series.daily_incidents(cv.incidents_stream(spark, d))
    dense = series.densify(daily, "2024-01-01", "2024-01-30", ("n_incidents",))
    return series.rolling(dense, ("n_incidents",), 7, min_periods=1).select("group_id", "day", F.col("n_incidents").alias("r_incidents"))


def w25_spearman_table(spark: SparkSession, d: str) -> DataFrame:
    return series.correlation_table(_focal(_paired(spark, d)))


def w25b_pearson_table(spark: SparkSession, d: str) -> DataFrame:
    return pearson(series.long_form(_focal(_paired(spark, d))), "value", "r_incidents", ["group_id", "measure"])


def w26_spearman_p(spark: SparkSession, d: str) -> DataFrame:
    from discourselab.functions.stats import describe

    found = series.with_p(w25_spearman_table(spark, d))
    return found.withColumn("reading", describe(F.col("r_s"), F.col("p")))


def w27_lagged_spearman(spark: SparkSession, d: str) -> DataFrame:
    """Every lag of thirty days either way."""
    return series.lagged_spearman(_focal(_paired(spark, d)), list(range(-30, 31)))


def w27b_cross_group(spark: SparkSession, d: str) -> DataFrame:
    return series.cross_group_corr(_paired(spark, d), *cv.FOCAL)


def _long(spark: SparkSession, d: str) -> DataFrame:
    return series.long_form(_focal(_paired(spark, d)))


def w28_peaks(spark: SparkSession, d: str) -> DataFrame:
    return series.peaks(_long(spark, d))


def w28b_series_summary(spark: SparkSession, d: str) -> DataFrame:
    return series.series_summary(_long(spark, d))


def w28c_decay(spark: SparkSession, d: str) -> DataFrame:
    return series.decay(_long(spark, d))


def w28d_event_window(spark: SparkSession, d: str) -> DataFrame:
    return series.event_window(_long(spark, d), _calendar(spark))


# graph


def _incident_rows(spark: SparkSession, d: str) -> DataFrame:
    """Incidents with a key: the row's columns and its number among equal rows."""
    inc = _clipped(spark, d)
    n = F.row_number().over(inc_window())
    return (
        inc.withColumn("_n", n)
        .select(
            F.concat_ws(
                "|",
                F.col("day").cast("string"),
                "motive",
                "offence",
                F.col("severity").cast("long").cast("string"),
                F.col("_n").cast("string"),
            ).alias("incident_id"),
            "day",
            "group_id",
        )
    )


def inc_window():
    from pyspark.sql.window import Window

    return Window.partitionBy("day", "motive", "offence", "severity").orderBy("group_id")


def _edges(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events")
    tagged = events.select(F.col("event_id").alias("post_id"), F.concat(F.lit("k"), F.get_json_object("props", "$.k")).alias("tag"))
    pages = cv.links(spark, d).select(F.col("author").alias("src_user"), F.explode("tags").alias("dst_user"))
    return graph.build_edges(
        cv.posts_retail(spark, d),
        cv.membership_retail(spark, d),
        cv.topic_groups(spark),
        _incident_rows(spark, d),
        tagged,
        cv.replies_stream(spark, d),
        pages,
    )


def w29_kg_nodes(spark: SparkSession, d: str) -> DataFrame:
    return graph.build_nodes(_edges(spark, d))


def w29b_kg_node_props(spark: SparkSession, d: str) -> DataFrame:
    """Nodes with what is known of them, written as name=value."""
    facts = graph.node_facts(cv.posts_retail(spark, d), _incident_rows(spark, d), cv.topic_groups(spark))
    nodes = graph.describe_nodes(graph.build_nodes(_edges(spark, d)), facts)
    shown = F.array_join(F.transform(F.array_sort(F.map_entries("props")), lambda e: F.concat_ws("=", e["key"], e["value"])), ",")
    return nodes.select("node_id", "kind", "key", shown.alias("props"))


def w30b_thread_edges(spark: SparkSession, d: str) -> DataFrame:
    """Who answers whom in conversations."""
    turns = cv.threads(spark, d)
    before = turns.select(F.col("post_id").alias("reply_to"), F.col("author_id").alias("dst_user"))
    return graph.e_between_users(turns.join(before, "reply_to").select(F.col("author_id").alias("src_user"), "dst_user"), "replied_to")


def w30c_written_graph(spark: SparkSession, d: str) -> DataFrame:
    """Relations read back from a graph written by relation."""
    path = scratch(spark, "graph")
    graph.write_graph(_edges(spark, d), path)
    return (
        spark.read
        .parquet(path)
        .where("rel in ('victimized', 'associated_with')")
        .groupBy("rel")
        .agg(F.count("*").alias("n"), F.sum("weight").alias("weight"))
    )


def w30d_dated_edges(spark: SparkSession, d: str) -> DataFrame:
    """Edges with a day, by relation and month."""
    dated = graph.with_day(_edges(spark, d))
    return dated.groupBy("rel", F.trunc("day", "month").alias("month")).agg(F.count("*").alias("n"))


def w30_kg_edges(spark: SparkSession, d: str) -> DataFrame:
    return _edges(spark, d)


def w31_kg_stats(spark: SparkSession, d: str) -> DataFrame:
    edges = _edges(spark, d)
    return graph.graph_stats(graph.build_nodes(edges), edges)


def w31b_kg_checks(spark: SparkSession, d: str) -> DataFrame:
    edges = _edges(spark, d)
    return graph.check_graph(graph.build_nodes(edges), edges)


def w32_kg_mean_topics(spark: SparkSession, d: str) -> DataFrame:
    return graph.mean_topics(_edges(spark, d))


def w33_date_bridge(spark: SparkSession, d: str) -> DataFrame:
    return (
        graph.date_bridge(_edges(spark, d))
        .select(
            F.to_date(F.substring_index("day", ":", -1)).alias("day"),
            F.substring_index("group", ":", -1).cast("int").alias("group_id"),
            "n_posts",
            "n_incidents",
        )
    )


def w34_match_path(spark: SparkSession, d: str) -> DataFrame:
    found = graph.match_path(_edges(spark, d), ("tweeted", "in_topic", "associated_with"))
    return found.select(
        F.substring_index("first", ":", -1).cast("long").alias("user_id"),
        F.substring_index("last", ":", -1).cast("int").alias("group_id"),
        "paths",
    )


def w34b_subgraph(spark: SparkSession, d: str) -> DataFrame:
    return graph.subgraph(_edges(spark, d), ("tweeted", "in_topic"), 0).groupBy("rel").agg(F.count("*").alias("n"))


def w34d_subgraph_period(spark: SparkSession, d: str) -> DataFrame:
    """A group's posts and memberships of one quarter."""
    held = graph.subgraph(graph.with_day(_edges(spark, d)), ("tweeted", "in_topic"), 0, ("1996-01-01", "1996-03-31"))
    return held.groupBy("rel").agg(F.count("*").alias("n"))


def w34c_cluster_profile(spark: SparkSession, d: str) -> DataFrame:
    posts = cv.posts_retail(spark, d)
    return graph.cluster_profile(posts, cv.membership_retail(spark, d), influence.active_users(posts, 15).select("user_id"))


# communities


def _topics_of(spark: SparkSession, group: int) -> DataFrame:
    return cv.topic_groups(spark).where(F.col("group_id") == group).select("topic_id")


def _snapshots(spark: SparkSession, d: str, group: int, period: str, start: str, end: str, mode: str = "unit", replies: bool = False) -> DataFrame:
    posts = select.clip_period(cv.posts_retail(spark, d), "day", start, end)
    answers = select.clip_period(cv.replies_retail(spark, d), "day", start, end) if replies else None
    members = cv.membership_retail(spark, d, posts=posts)
    return community.snapshots(posts, members, _topics_of(spark, group), period, mode, answers)


def w35_snapshots(spark: SparkSession, d: str) -> DataFrame:
    return _snapshots(spark, d, 0, "month", "1996-01-01", "1996-06-30")


def w35c_snapshots_replies(spark: SparkSession, d: str) -> DataFrame:
    """Snapshots with edges between users as well."""
    return _snapshots(spark, d, 0, "month", "1996-01-01", "1996-06-30", replies=True)


def w35b_snapshots_stream(spark: SparkSession, d: str) -> DataFrame:
    user = lambda c: F.concat(F.lit("user:"), F.col(c).cast("string"))
    pairs = cv.replies_stream(spark, d).select(F.to_date(F.date_trunc("week", "day")).alias("period"), user("src_user").alias("a"), user("dst_user").alias("b"))
    return pairs.groupBy("period", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.count("*").cast("double").alias("weight"))


def w36_components(spark: SparkSession, d: str) -> DataFrame:
    return community.period_components(w35b_snapshots_stream(spark, d))


def _quality_of(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(period, nodes, communities, modularity)."""
    held = labels.groupBy("period").agg(F.count("*").alias("nodes"), F.count_distinct("community").alias("communities"))
    return held.join(community.modularity(edges, labels), "period").select("period", "nodes", "communities", "modularity")


def w37_louvain_month(spark: SparkSession, d: str) -> DataFrame:
    """Louvain of one month and one quarter of both focal groups."""
    out = None
    for group in cv.FOCAL:
        for period, end in (("month", "1996-01-31"), ("quarter", "1996-03-31")):
            edges = _snapshots(spark, d, group, period, "1996-01-01", end)
            part = _quality_of(edges, community.louvain(edges)).select(F.lit(group).alias("group_id"), F.lit(period).alias("span"), "*")
            out = part if out is None else out.unionByName(part)
    return out


def w37c_louvain_joins(spark: SparkSession, d: str) -> DataFrame:
    """Louvain by joins, for snapshots that no task could hold, on one month."""
    edges = _snapshots(spark, d, 0, "month", "1996-03-01", "1996-03-31")
    return _quality_of(edges, community.louvain_distributed(edges))


def w37d_label_propagation(spark: SparkSession, d: str) -> DataFrame:
    """The edges are written once, and both the labels and their quality read them."""
    edges = settle(_snapshots(spark, d, 0, "month", "1996-03-01", "1996-03-31"))
    return _quality_of(edges, community.label_propagation(edges))


def w37b_louvain_weighted(spark: SparkSession, d: str) -> DataFrame:
    edges = _snapshots(spark, d, 0, "month", "1996-03-01", "1996-03-31", "prob")
    labels = community.louvain(edges)
    return labels.groupBy("period", "community").agg(F.count("*").alias("size"))


def _given_labels(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Snapshots of a quarter, and labels by dominant topic of each post and user."""
    posts = select.clip_period(cv.posts_retail(spark, d), "day", "1996-01-01", "1996-12-31")
    inside = (
        cv.membership_retail(spark, d)
        .join(F.broadcast(_topics_of(spark, 0)), "topic_id", "left_semi")
        .join(posts, "post_id")
        .withColumn("period", F.to_date(F.date_trunc("quarter", "day")))
    )
    top = lambda key, kind: inside.groupBy("period", key, "topic_id").agg(F.sum("p").alias("p")).groupBy("period", key).agg(F.max(F.struct(F.round("p", 9).alias("p"), (-F.col("topic_id")).alias("t"))).alias("m")).select("period", F.concat(F.lit(f"{kind}:"), F.col(key).cast("string")).alias("node"), (-F.col("m.t")).alias("community"))
    own = inside.select("period", F.concat(F.lit("topic:"), F.col("topic_id").cast("string")).alias("node"), F.col("topic_id").alias("community")).distinct()
    return _snapshots(spark, d, 0, "quarter", "1996-01-01", "1996-12-31"), top("post_id", "post").unionByName(top("author_id", "user")).unionByName(own)


def w38_modularity_given_labels(spark: SparkSession, d: str) -> DataFrame:
    return community.modularity(*_given_labels(spark, d))


def _dominant(spark: SparkSession, d: str, period: str, by_topic: bool, floor: int) -> DataFrame:
    """(period, community, user_id): the group or topic a user writes most about in a period."""
    members = cv.membership_retail(spark, d).join(cv.posts_retail(spark, d), "post_id")
    kind = "topic_id" if by_topic else "group_id"
    held = members if by_topic else members.join(F.broadcast(cv.topic_groups(spark)), "topic_id")
    summed = held.groupBy(F.to_date(F.date_trunc(period, "day")).alias("period"), F.col("author_id").alias("user_id"), kind).agg(F.sum("p").alias("p"))
    best = summed.groupBy("period", "user_id").agg(F.max(F.struct(F.round("p", 9).alias("p"), (-F.col(kind)).alias("k"))).alias("m"))
    return community.floor_size(best.select("period", (-F.col("m.k")).alias("community"), "user_id"), ["period"], floor)


def w39_jaccard_links(spark: SparkSession, d: str) -> DataFrame:
    return community.evolve(_dominant(spark, d, "quarter", False, 50), 3, 0.01)


def w39b_jaccard_links_month(spark: SparkSession, d: str) -> DataFrame:
    return community.evolve(_dominant(spark, d, "month", True, 5), 1, 0.05)


def w40_evolution_types(spark: SparkSession, d: str) -> DataFrame:
    users = _dominant(spark, d, "month", True, 5)
    return community.classify_evolution(users, community.evolve(users, 1, 0.08), 1)


def w40b_lifespans(spark: SparkSession, d: str) -> DataFrame:
    users = _dominant(spark, d, "quarter", False, 50)
    return community.lifespans(users, community.evolve(users, 3, 0.2), 3)


def w41_community_sentiment(spark: SparkSession, d: str) -> DataFrame:
    scores = cv.posts_retail(spark, d).groupBy(F.col("author_id").alias("user_id")).agg(F.avg("sentiment").alias("mean_score"))
    return community.community_nodes(_dominant(spark, d, "quarter", False, 50), scores)


# users


def _users(spark: SparkSession, d: str) -> DataFrame:
    return influence.active_users(cv.posts_retail(spark, d))


def _profiles(spark: SparkSession, d: str) -> DataFrame:
    return influence.user_profiles(cv.posts_retail(spark, d), cv.membership_retail(spark, d), _users(spark, d))


def _by_group(spark: SparkSession, d: str) -> DataFrame:
    return influence.restrict(_profiles(spark, d), cv.topic_groups(spark))


def _restricted(spark: SparkSession, d: str) -> DataFrame:
    return _focal(_by_group(spark, d))


def w42_active_users(spark: SparkSession, d: str) -> DataFrame:
    return _users(spark, d).select("user_id", "n_posts")


def w43_user_profiles(spark: SparkSession, d: str) -> DataFrame:
    """Profiles over memberships in millionths, whose sums are exact."""
    members = cv.membership_retail(spark, d).withColumn("p", F.round(F.col("p") * 1e6))
    return influence.user_profiles(cv.posts_retail(spark, d), members, _users(spark, d)).withColumn("s", F.col("s") / 1e6)


def w44_pair_weights(spark: SparkSession, d: str) -> DataFrame:
    """The networks of all groups, focal or not."""
    return influence.pair_weights(_by_group(spark, d))


def w45_pair_weights_naive(spark: SparkSession, d: str) -> DataFrame:
    """The definition, over all active users: a baseline whose cost grows with the square of the posts."""
    return influence.pair_weight_naive(cv.posts_retail(spark, d), cv.membership_retail(spark, d), _users(spark, d).select("user_id"))


def w45b_pair_weights_factorised(spark: SparkSession, d: str) -> DataFrame:
    return influence.pair_weights(_profiles(spark, d), ())


def w45c_no_activity_floor(spark: SparkSession, d: str) -> DataFrame:
    """Weighted degrees of the network of all users, whatever they post: the baseline without the floor."""
    posts, members = cv.posts_retail(spark, d), cv.membership_retail(spark, d)
    everyone = posts.select(F.col("author_id").alias("user_id")).distinct()
    return influence.weighted_degree(_focal(influence.restrict(influence.user_profiles(posts, members, everyone), cv.topic_groups(spark))))


def w46_weighted_degree(spark: SparkSession, d: str) -> DataFrame:
    return influence.weighted_degree(_restricted(spark, d))


def _centrality(spark: SparkSession, d: str) -> DataFrame:
    return influence.eigen_centrality_steps(_restricted(spark, d), EIGEN_STEPS)


def w47_eigen_centrality(spark: SparkSession, d: str) -> DataFrame:
    return _centrality(spark, d)


def w47b_eigen_converged(spark: SparkSession, d: str) -> DataFrame:
    return influence.eigen_centrality(_restricted(spark, d))


def w47c_eigen_residual(spark: SparkSession, d: str) -> DataFrame:
    held = _restricted(spark, d)
    return influence.eigen_residual(held, influence.eigen_centrality(held)).select("group_id", (F.col("residual") < 1e-6).alias("settled"))


def _influence(spark: SparkSession, d: str) -> DataFrame:
    return influence.influence(_centrality(spark, d), _users(spark, d), cv.profiles(spark, d))


def w48_influence_top5(spark: SparkSession, d: str) -> DataFrame:
    return influence.top_influencers(_influence(spark, d))


def w48b_rank_overlap(spark: SparkSession, d: str) -> DataFrame:
    """Overlap at five of influence with centrality, follower and post-count rankings."""
    scored = _influence(spark, d)
    top = influence.rank_by(scored, "influence")
    out = None
    for name in ("centrality", "followers", "n_posts"):
        part = influence.overlap_at(top, influence.rank_by(scored, name), 5).select(F.lit(name).alias("ranking"), "group_id", "overlap")
        out = part if out is None else out.unionByName(part)
    return out


def w49_influence_bins(spark: SparkSession, d: str) -> DataFrame:
    return influence.influence_by_sentiment(_influence(spark, d))


def w49b_group_contrast(spark: SparkSession, d: str) -> DataFrame:
    scored = _influence(spark, d)
    bins = influence.bin_error_contrast(influence.influence_by_sentiment(scored))
    return influence.group_contrast(influence.top_influencers(scored)).join(bins, "group_id")


def w50_toxic_precision_recall(spark: SparkSession, d: str) -> DataFrame:
    ten = spark.createDataFrame([(w,) for w in cv.DEROGATORY], "term string")
    docs = table(spark, d, "documents")
    matched = select.match_terms(docs, ten, "doc_id", "text")
    return measures.match_quality(matched, cv.truth(spark, d).join(docs.select("doc_id", "lang"), "doc_id"), "lang")


def w51_stream_daily_counts(spark: SparkSession, d: str) -> DataFrame:
    return monitor.daily_counts(spark, d)


def w53_corpus_stats(spark: SparkSession, d: str) -> DataFrame:
    return measures.corpus_stats(cv.posts_retail(spark, d), cv.membership_retail(spark, d))


def w54_distributed_rank(spark: SparkSession, d: str) -> DataFrame:
    from discourselab.functions.stats import distributed_rank

    return distributed_rank(table(spark, d, "orders"), "o_totalprice").select(F.col("o_totalprice").alias("price"), "rank")


#: The converged workload and the clustering comparison stop on a tolerance and have no SQL.
_WORKLOADS = [f for name, f in sorted(globals().items()) if name[:1] == "w" and name[1:3].isdigit()]


def _tidied(f: Query) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return tidy(f(prepare(spark), sf_dir))

    query.__name__, query.__doc__ = f.__name__, f.__doc__
    return query


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most influential users of each focal group."""
    return tidy(w48_influence_top5(spark, sf_dir))


def queries() -> dict[str, Query]:
    return {f.__name__: _tidied(f) for f in _WORKLOADS} | {name: _tidied(f) for name, f in general.queries().items()}


def oracle_sql() -> dict[str, str]:
    return oracles.workload_sql() | general.oracle_sql()


