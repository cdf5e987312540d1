"""The whole job where older queries read a part: brute force on small tables."""

import gc
import math
import random
import time
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from discourselab import workloads
from discourselab.operators import influence
from discourselab.session import shared_base
from discourselab.sources import carriers as cv


@pytest.fixture(scope="module")
def long_texts(spark, tmp_path_factory):
    """Three texts that agree in their first 300 characters and differ after them."""
    d = str(tmp_path_factory.mktemp("long"))
    texts = ["zz " * 100 + end for end in ("idiot scum", "ther marvel", "ther marvel")]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{d}/documents.parquet")
    spark.range(3).select(F.col("id").alias("event_id")).write.parquet(f"{d}/events.parquet")
    spark.createDataFrame([(0, 0), (1, 1), (2, 1)], "vec_id long, label int").write.parquet(f"{d}/embeddings.parquet")
    return d


def test_words_after_the_opening_are_scored(spark, long_texts):
    n = lambda x: round(x / math.sqrt(x * x + 15), 6)
    for name in ("w09_sentiment_rules", "w10_sentiment_plain"):
        found = {r.post_id: r.score for r in workloads.queries()[name](spark, long_texts).collect()}
        assert found == {0: n(-2.3 - 2.9), 1: n(1.9), 2: n(1.9)}


def test_terms_after_the_opening_are_counted(spark, long_texts):
    q = workloads.queries()
    found = {(r.topic_id, r.term): r.weight for r in q["w15_class_tfidf"](spark, long_texts).collect()}
    mean = (3 * 102 - 3) * 3 / 2  # one-, two- and three-word terms of three texts of 102 words, by two topics
    assert found[0, "idiot scum"] == pytest.approx(math.log(1 + mean / 1), abs=1e-6)
    assert found[1, "ther marvel"] == pytest.approx(2 * math.log(1 + mean / 2), abs=1e-6)
    names = {r.topic_id: r.label for r in q["w16_topic_names"](spark, long_texts).collect()}
    assert "scum" in names[0] and "marvel" in names[1]
    noise = {r.topic_id: (r.n, r.distinct_texts, r.noise) for r in q["w17b_noise_topics"](spark, long_texts).collect()}
    assert noise == {0: (1, 1, False), 1: (2, 1, True)}


def test_every_lag_is_there(spark, small):
    rows = workloads.queries()["w27_lagged_spearman"](spark, small).collect()
    assert {r.lag for r in rows} == set(range(-30, 31))


def test_factorised_weights_equal_naive_ones_of_all_users(spark, small):
    posts, members = cv.posts_retail(spark, small), cv.membership_retail(spark, small)
    users = influence.active_users(posts).select("user_id")
    naive = {(r.a, r.b): r.weight for r in influence.pair_weight_naive(posts, members, users).collect()}
    profiles = influence.user_profiles(posts, members, users)
    for cell in (20_000, 50):
        found = {(r.a, r.b): r.weight for r in influence.pair_weights(profiles, (), cell).collect()}
        assert users.count() > 30 and found == pytest.approx(naive)


def joined_weights(profiles, by):
    """The definition by a join of profiles."""
    left = profiles.select(*by, F.col("user_id").alias("a"), "topic_id", F.col("s").alias("x"))
    right = profiles.select(*by, F.col("user_id").alias("b"), "topic_id", F.col("s").alias("y"))
    met = left.join(right, [*by, "topic_id"]).where("a < b").groupBy(*by, "a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("weight"))
    return {tuple(r[:-1]): r.weight for r in met.collect()}


def shuffles(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange")


@pytest.mark.parametrize("values", [(0.0, 1.0, -2.0, 0.5), (None, 0.0, 1.0), (None, 0.0, 3.0, float("inf"), float("nan"))])
def test_pairs_are_made_once_and_never_shuffled(spark, values):
    """Keys and values may be null, weights may be zero; a pair is there if it shares a topic."""
    rng = random.Random(5)
    keys = {(rng.choice([0, 1, None]), rng.choice([*range(30), None]), rng.choice([1, 2, 3, 8, 9, None])) for _ in range(200)}
    rows = [(*k, rng.choice(values)) for k in sorted(keys, key=str)]
    profiles = spark.createDataFrame(rows, "group_id int, user_id long, topic_id int, s double")
    expected = joined_weights(profiles, ("group_id",))
    for cell in (20_000, 20):
        df = influence.pair_weights(profiles, ("group_id",), cell)
        assert shuffles(df) == 0
        found = {tuple(r[:-1]): r.weight for r in df.collect()}
        assert len(found) > 100 and found == pytest.approx(expected, nan_ok=True)


def test_every_pair_of_posts_counts_without_a_shuffle_of_pairs(spark):
    """Posts of many sizes; some users share no topic, and two write the same."""
    rng = random.Random(7)
    posts = [(p, rng.choice([0, 1, 1, 1, *range(2, 25), None])) for p in range(150)]
    members = sorted({(p, rng.randrange(12)) for p, _ in posts for _ in range(rng.choice([0, 1, 1, 3]))})
    p = {k: rng.choice([0.0, 0.25, 0.5, 1.0, None]) for k in members}
    users = [*range(20), None]
    wrote = spark.createDataFrame(posts, "post_id long, author_id long")
    about = spark.createDataFrame([(*k, v) for k, v in p.items()], "post_id long, topic_id int, p double")
    expected, author = {}, dict(posts)
    for (one, topic), x in p.items():
        for (other, same), y in p.items():
            a, b = author[one], author[other]
            if topic == same and a in users and b in users and a is not None and b is not None and a < b:
                term = None if x is None or y is None else x * y
                before = expected.get((a, b))
                expected[a, b] = before if term is None else (before or 0.0) + term
    for cell in (20_000, 30):
        df = influence.pair_weight_naive(wrote, about, spark.createDataFrame([(u,) for u in users], "user_id long"), cell)
        assert shuffles(df) == 0
        found = {(r.a, r.b): r.weight for r in df.collect()}
        assert len(found) > 50 and found == pytest.approx(expected)


def test_label_propagation_sends_no_labels_to_the_driver_and_reads_lines_once(spark, small):
    df = workloads.queries()["w37d_label_propagation"](spark, small)
    assert not any("lineitem" in f for f in df.inputFiles())
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("SortMergeJoin") >= 2 and "modularity" in df.columns
    assert df.count() == 1


def test_memberships_of_some_posts_are_those_of_all(spark, small):
    posts = cv.posts_retail(spark, small).where("post_id % 3 = 1")
    some = {(r.post_id, r.topic_id, r.p) for r in cv.membership_retail(spark, small, posts=posts).collect()}
    assert some and some == {(r.post_id, r.topic_id, r.p) for r in cv.membership_retail(spark, small).where("post_id % 3 = 1").collect()}


def test_recursion_reads_all_orders(spark, small):
    rows = workloads.queries()["op_recursive_cte"](spark, small).collect()
    n = spark.read.parquet(f"{small}/orders.parquet").count()
    assert len(rows) == 12 and {r.n for r in rows} == {n} and 0 < sum(r.held for r in rows) <= n


@pytest.mark.parametrize("name", ["op_replay_source", "op_stream_replay"])
def test_all_events_are_replayed(spark, small, name):
    whole = spark.read.parquet(f"{small}/events.parquet").select("event_id", "user_id", "event_type", F.round("value", 6).alias("value"))
    df = workloads.queries()[name](spark, small)
    assert df.count() == whole.count() and df.exceptAll(whole).isEmpty()


def test_the_rate_source_numbers_all_events(spark, small):
    found = sorted(r.value for r in workloads.queries()["op_stream_rate"](spark, small).collect())
    assert found == sorted(r.event_id for r in spark.read.parquet(f"{small}/events.parquet").select("event_id").collect())


def test_weights_of_all_topics_are_made_without_a_shuffle_of_pairs(spark, small):
    df = workloads.queries()["w45b_pair_weights_factorised"](spark, small)
    assert shuffles(df) == 0 and df.select("a", "b").distinct().count() == df.count()


def test_many_pairs_come_in_few_files_and_few_pairs_in_a_task_for_each_core(spark):
    blocks = influence._blocks(1_033_794, 48_660, 48_660, 20_000, 6)
    assert 48_660**2 / blocks**2 < 1.1 * influence.PAIRS and blocks * (blocks + 1) // 2 < 200
    assert influence._blocks(172_299, 8_110, 8_110, 20_000, 6) == 8
    assert influence._blocks(0, 0, 0, 20_000, 6) == influence._blocks(20_000, 800, 800, 20_000, 6) == 1
    assert influence._blocks(8_000_000, 1_000, 1_000, 20_000, 6) == 50


def test_users_of_many_topics_meet_in_large_blocks(spark):
    """26,000 rows of 260 users were 26 blocks of 1,000 rows, or 676 tasks, for 33,670 pairs."""
    profiles = spark.range(26_000).selectExpr("id div 100 as user_id", "cast(id % 100 as int) as topic_id", "1.0d + id % 7 as s")
    df = influence.pair_weights(profiles, (), 1_000)
    cores = spark.sparkContext.defaultParallelism
    assert df.rdd.getNumPartitions() <= max(4 * influence.TASKS * cores, 16)
    found = {(r.a, r.b): r.weight for r in df.collect()}
    assert found == pytest.approx({k[-2:]: v for k, v in joined_weights(profiles, ()).items()}) and len(found) == 260 * 259 // 2


def test_every_group_has_its_pair_weights(spark, small):
    """Three of the five groups were left out."""
    posts, groups = cv.posts_retail(spark, small), cv.topic_groups(spark)
    profiles = influence.user_profiles(posts, cv.membership_retail(spark, small), influence.active_users(posts))
    expected = joined_weights(influence.restrict(profiles, groups), ("group_id",))
    found = {tuple(r)[:3]: r.weight for r in workloads.queries()["w44_pair_weights"](spark, small).select("group_id", "a", "b", "weight").collect()}
    assert {g for g, _, _ in found} == {r.group_id for r in groups.collect()} == set(range(5))
    assert found == pytest.approx(expected, abs=1e-6)


def test_lines_are_shuffled_by_post_once(spark, small):
    """They were shuffled by post and topic, and then by post."""
    posts = cv.posts_retail(spark, small).hint("merge")
    plan = cv.membership_retail(spark, small).join(posts, "post_id")._jdf.queryExecution().executedPlan().toString()
    assert "Window" in plan and plan.count("Exchange hashpartitioning") == 2


def test_blocks_leave_no_shuffle_files_and_no_rows(spark, small):
    """They stayed while pairs were made."""
    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    shared = Path(shared_base(spark).removeprefix("file:"))
    files = lambda: {f for d in disk.localDirs() for f in Path(str(d)).glob("*/shuffle_*.data")} | set(shared.glob("pairs-rows-*"))
    gc.collect()
    before = files()
    dfs = [workloads.queries()[f"w4{name}"](spark, small) for name in ("4_pair_weights", "5_pair_weights_naive", "5b_pair_weights_factorised")]
    for _ in range(50):
        if not files() - before:
            break
        time.sleep(0.2)
    assert not files() - before and all(not df.isEmpty() for df in dfs)
