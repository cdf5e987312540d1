"""Identities, invariants and known small cases of the methods."""

import datetime
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from discourselab import workloads
from discourselab.functions import text as tx
from discourselab.functions.stats import distributed_rank, spearman
from discourselab.operators import community, graph, influence, measures, select, series, topics
from discourselab.plans.iterate import components
from discourselab.sources import carriers as cv
from discourselab.streaming import monitor

DAY = datetime.date(1996, 1, 1)


def one(df):
    return df.collect()[0]


def test_clean_and_expand(spark):
    d = spark.createDataFrame([("  Don't-STOP  ❤ Été 42!",), (None,), ("",), ("!!",)], "t string")
    assert [r[0] for r in d.select(tx.clean_text(F.col("t"))).collect()] == ["dontstop été 42", None, "", ""]
    assert one(d.select(tx.clean_text(F.col("t"), True)))[0] == "dont-stop été 42"
    terms = tx.expand_terms(spark.createDataFrame([("clown",), ("black box",)], "base string"))
    assert {r.base: r.n for r in terms.groupBy("base").agg(F.count("*").alias("n")).collect()} == {"clown": 2, "black box": 6}


def test_token_mode_equals_boundary_regex(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", F.substring("text", 1, 300).alias("text"))
    terms = spark.createDataFrame([("the",), ("stupid",), ("of the",), ("é",)], "term string")
    token, regex, sub = (set(map(tuple, select.match_terms(docs, terms, "doc_id", "text", mode).collect())) for mode in ("token", "regex", "substring"))
    assert token == regex and token < sub


def test_sentiment_rules(spark):
    lexicon, rules = {"good": 2.0, "bad": -2.0}, tx.Rules(degree={"very": 0.293}, negation=("not",), contrast=("but",))
    texts = ["good", "very good", "not good", "bad but good", "GOOD day", "good!!!!!", "good??", None, "", "so x"]
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, t string")
    s = [r[1] for r in d.select("i", tx.sentiment(F.col("t"), lexicon, rules)).orderBy("i").collect()]
    n = lambda x: x / math.sqrt(x * x + 15)
    expected = [n(2), n(2.293), n(-1.48), n(-1 + 3), n(2.733), n(2 + 4 * 0.292), n(2.36), 0, 0, 0]
    assert s == pytest.approx(expected)
    assert all(-1 <= x <= 1 for x in s)


def test_spearman_ties_constant_and_monotone(spark):
    d = spark.createDataFrame([("a", 1.0, 1.0), ("a", 2.0, 3.0), ("a", 2.0, 3.0), ("a", 3.0, 2.0), ("a", None, 5.0), ("b", 1.0, 1.0), ("b", 1.0, 2.0)], "g string, x double, y double")
    r = {x.g: x for x in spearman(d, "x", "y", ["g"]).collect()}
    ranks = np.corrcoef([1, 2.5, 2.5, 4], [1, 3.5, 3.5, 2])[0, 1]
    assert r["a"].n == 4 and r["a"].r_s == pytest.approx(ranks) and r["b"].r_s is None
    cubed = d.withColumn("x", F.col("x") ** 3)
    assert {x.g: x.r_s for x in spearman(cubed, "x", "y", ["g"]).collect()}["a"] == pytest.approx(ranks)


def test_distributed_rank_equals_window(spark):
    d = spark.range(500).select((F.col("id") * 37 % 91).alias("v"))
    found = {r.v: r["rank"] for r in distributed_rank(d, "v").collect()}
    values = np.array([i * 37 % 91 for i in range(500)])
    for v, rank in found.items():
        assert rank == (values < v).sum() + ((values == v).sum() + 1) / 2


def test_spine_rolling_and_range_frame(spark):
    rows = [(1, DAY + datetime.timedelta(k), k + 1) for k in range(40)]
    s = spark.createDataFrame(rows, "group_id int, day date, n long")
    rolled = series.rolling(series.densify(s, "1996-01-01", "1996-02-09", ("n",)), ("n",), 30, min_periods=5)
    values = [r.n for r in rolled.orderBy("day").collect()]
    assert values[:4] == [None] * 4 and values[-1] == 25.5
    ranged = [r[0] for r in s.orderBy("day").select(series.rolling_by_range(s, "n", 30).alias("x")).collect()]
    assert ranged[-1] == 25.5
    holes = series.densify(s.where("n not in (2, 4)").withColumn("m", F.col("n") * 1.0), "1996-01-01", "1996-01-05", ("n",))
    assert [(r.n, r.m) for r in holes.orderBy("day").collect()] == [(1, 1.0), (0, None), (3, 3.0), (0, None), (5, 5.0)]


def test_louvain_known_graphs(spark):
    clique = lambda p, n: [(f"{p}{i}", f"{p}{j}", 1.0) for i in range(n) for j in range(i)]
    edges = [*clique("a", 5), *clique("b", 5), ("a0", "b0", 1.0)]
    d = spark.createDataFrame([(DAY, *e) for e in edges], "period date, src string, dst string, weight double")
    for labels in (community.louvain(d), community.louvain_distributed(d)):
        held = {r.node: r.community for r in labels.collect()}
        assert len(set(held.values())) == 2 and len({held[f"a{i}"] for i in range(5)}) == 1
        assert one(community.modularity(d, labels)).modularity == pytest.approx(20 / 21 - 0.5)
    assert community.louvain_labels([]) == {} and len(set(community.louvain_labels([("x", "y", 1.0)]).values())) == 1


def test_louvain_on_a_month_stays_within_components(spark, small):
    posts = select.clip_period(cv.posts_retail(spark, small), "day", "1996-01-01", "1996-12-31")
    topic = cv.topic_groups(spark).where("group_id = 0").select("topic_id")
    edges = community.snapshots(posts, cv.membership_retail(spark, small), topic, "year")
    labels = community.louvain(edges)
    q = one(community.modularity(edges, labels)).modularity
    assert q > 0.5 and labels.count() == labels.select("node").distinct().count()
    parts = {r.node: r.label for r in components(edges).collect()}
    assert all(parts[r.node] == parts[r.community] for r in labels.collect())


def test_components(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101), (7, 7)], "src long, dst long")
    found = {r.node: r.label for r in components(chain).collect()}
    assert set(found.values()) == {0, 100} and found[60] == 0


def test_evolution_and_jaccard_bruteforce(spark):
    def rows(period, **sets):
        return [(period, c, u) for c, users in sets.items() for u in users]

    feb = datetime.date(1996, 2, 1)
    users = spark.createDataFrame([*rows(DAY, A=[1, 2, 3, 4], D=[5, 6], E=[7, 8], H=[20]), *rows(feb, B=[1, 2], C=[3, 4], F=[5, 6, 7, 8], G=[30])], "period date, community string, user_id int")
    links = community.evolve(users, 1, 0.01)
    assert {tuple(r) for r in links.collect()} == {tuple(r) for r in community.evolve_bruteforce(users, 1, 0.01).collect()}
    events = {(r.community, r.event) for r in community.classify_evolution(users, links, 1).collect()}
    assert {("A", "split"), ("F", "merge"), ("G", "birth"), ("H", "death"), ("D", "continue")} <= events
    assert {r.community: r.length for r in community.lifespans(users, links, 1).collect()}["F"] == 2
    a, b = (spark.createDataFrame([(x,) for x in s], "u int") for s in ([1, 2, 3], [2, 3, 4]))
    assert one(measures.jaccard(a, b, "u")).jaccard == 0.5


def test_pair_weights_and_centrality(spark):
    p = spark.createDataFrame([(0, 1, 1, 1.0), (0, 1, 2, 2.0), (0, 2, 1, 3.0), (0, 2, 2, 4.0)], "group_id int, user_id long, topic_id int, s double")
    assert one(influence.pair_weights(p)).weight == 11.0
    assert {r.user_id: r.degree for r in influence.weighted_degree(p).collect()} == {1: 11.0, 2: 11.0}
    found = {r.user_id: r.centrality for r in influence.eigen_centrality(p, shift=11.0).collect()}
    assert found == pytest.approx({1: 2**-0.5, 2: 2**-0.5})
    n = 4
    star = spark.createDataFrame([("hub", f"leaf{i}", 1.0) for i in range(n)], "src string, dst string, weight double")
    c = {r.node: r.centrality for r in influence.eigen_centrality_edges(star, 60).collect()}
    assert c["hub"] == pytest.approx(2**-0.5, abs=1e-6) and c["leaf0"] == pytest.approx((2 * n) ** -0.5, abs=1e-6)


def test_implicit_centrality_equals_dense(spark, small):
    users = influence.active_users(cv.posts_retail(spark, small))
    held = influence.restrict(influence.user_profiles(cv.posts_retail(spark, small), cv.membership_retail(spark, small), users), cv.topic_groups(spark)).where("group_id = 0")
    rows = held.collect()
    ids = sorted({r.user_id for r in rows})
    s = np.zeros((len(ids), 26))
    for r in rows:
        s[ids.index(r.user_id), r.topic_id] = r.s
    w = s @ s.T
    np.fill_diagonal(w, 0)
    dense = influence.eigen_dense(w)
    found = {r.user_id: r.centrality for r in influence.eigen_centrality(held, tol=1e-10).collect()}
    assert np.allclose([found[i] for i in ids], dense, atol=1e-6)
    naive = {(r.a, r.b): r.weight for r in influence.pair_weight_naive(cv.posts_retail(spark, small), cv.membership_retail(spark, small), users.select("user_id").orderBy("user_id").limit(8)).collect()}
    profile = influence.user_profiles(cv.posts_retail(spark, small), cv.membership_retail(spark, small), users.select("user_id").orderBy("user_id").limit(8))
    assert naive == pytest.approx({(r.a, r.b): r.weight for r in influence.pair_weights(profile, ()).collect()})


def test_small_bins_are_dropped(spark):
    d = spark.createDataFrame([(0, 0.05, 1.0)] * 12 + [(0, 0.15, 9.0)] * 9, "group_id int, score double, influence double")
    rows = influence.influence_by_sentiment(d).collect()
    assert [(r.bin_lo, r.n, r.is_peak) for r in rows] == [(0.0, 12, True)]


def test_graph_by_hand(spark):
    posts = spark.createDataFrame([(1, 7, DAY, 0.1), (2, 8, DAY, 0.2)], "post_id long, author_id long, day date, sentiment double")
    members = spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 3, 1.0)], "post_id long, topic_id int, p double")
    groups = spark.createDataFrame([(1, 0), (2, 0), (3, 1)], "topic_id int, group_id int")
    inc = spark.createDataFrame([("i1", DAY, 0)], "incident_id string, day date, group_id int")
    edges = graph.build_edges(posts, members, groups, inc)
    assert {r.rel: r["count"] for r in edges.groupBy("rel").count().collect()} == {"tweeted": 2, "tweeted_on": 2, "in_topic": 3, "occurred_on": 1, "victimized": 1, "associated_with": 3}
    nodes = graph.build_nodes(edges)
    assert all(r.violations == 0 for r in graph.check_graph(nodes, edges).collect())
    assert {tuple(r)[1:] for r in graph.date_bridge(edges).collect()} == {("group:0", 1, 1)}


def test_membership_rows_and_clusters(spark, small):
    raw = spark.read.parquet(f"{small}/embeddings.parquet")
    soft = topics.soft_membership(raw, topics.centers(raw))
    assert soft.groupBy("vec_id").agg(F.sum("p").alias("s")).where("abs(s - 1) > 1e-9").count() == 0
    planted = topics.plant(raw, "label", 2.5)
    score = lambda found, v: one(measures.agreement(found, v.select("vec_id", "label")))
    assert score(topics.cluster_density(planted, 20), planted).ari > 0.5
    assert score(topics.cluster_centroid(planted, 10, 20), planted).ari > 0.5
    assert score(topics.random_topics(planted, 10), planted).ari < 0.1
    assert topics.reduce_dimensions(raw, 5).select(F.size("embedding")).first()[0] == 5
    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert topics.embed(docs, "doc_id", "text").select(F.size("embedding")).first()[0] == 64


def test_stream_restart_counts_once(spark, small, tmp_path):
    from discourselab.sources.files import event_stream

    for _ in range(2):  # the second run starts from the first one's checkpoint and finds nothing new
        query = event_stream(spark, small).select("event_id").writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
        query.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "out")).count() == spark.read.parquet(f"{small}/events.parquet").count()


@pytest.mark.parametrize("batches", [1, 6])
@pytest.mark.parametrize("name", ["op_stream_tumbling", "op_stream_sliding", "op_stream_session", "op_stream_dedup", "op_stream_stateful", "op_stream_stream_join", "op_stream_late", "w51_stream_daily_counts"])
def test_streams_do_not_depend_on_batches(spark, small, monkeypatch, name, batches):
    query = workloads.queries()[name]
    whole = sorted(map(str, query(spark, small).collect()))
    monkeypatch.setattr(monitor, "BATCHES", batches)
    assert whole and sorted(map(str, query(spark, small).collect())) == whole


def test_late_rows_are_dropped(spark, small):
    from discourselab.sources.files import event_stream

    late = F.col("event_id") % 50 == 0
    kept = monitor.drain(monitor.tumbling(event_stream(spark, small, 3, late))).agg(F.sum("n")).first()[0]
    every = monitor.drain(monitor.tumbling(event_stream(spark, small, 3))).agg(F.sum("n")).first()[0]
    assert 0 < kept < every


def test_running_state_with_rocksdb(spark, small):
    from discourselab.sources.files import event_stream

    name = "spark.sql.streaming.stateStore.providerClass"
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        found = {r.user_id: r.n for r in monitor.drain(monitor.running_profiles(event_stream(spark, small, 3)), "update", ("user_id",)).collect()}
        daily = event_stream(spark, small).select("event_type", F.to_date("ts").alias("day"), F.col("event_id").alias("n"))
        spiked = monitor.drain(monitor.spikes(daily, "event_type"), "update", ("key", "day", "n"))
        assert spiked.count() == sum(found.values())
    finally:
        spark.conf.unset(name)
    assert found == {r.user_id: r["count"] for r in spark.read.parquet(f"{small}/events.parquet").groupBy("user_id").count().collect()}


def test_plans_push_filters_and_read_few_columns(spark, small):
    from discourselab.operators.general import scan_prune

    plan = scan_prune(spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual" in plan and "l_comment" not in plan and "l_tax" not in plan


def test_measure_reports_a_run(spark, small):
    found = measures.measure(lambda: spark.read.parquet(f"{small}/orders.parquet").groupBy("o_custkey").count())
    assert found["rows"] == 150 or found["rows"] > 0
    assert found["stages"] >= 1


@pytest.mark.parametrize("planted", [True, False])
def test_neighbour_search_finds_the_nearest(spark, planted):
    vectors = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    vectors = topics.plant(vectors, "label", 2.5) if planted else vectors
    rows = {r.vec_id: np.array(r.embedding, float) for r in vectors.collect()}
    ids, unit = np.array(list(rows)), np.stack([x / np.linalg.norm(x) for x in rows.values()])
    score = unit @ unit.T
    np.fill_diagonal(score, -9)
    nearest = {int(i): set(ids[np.argsort(-s)[:10]].tolist()) for i, s in zip(ids, score, strict=True)}
    found = topics.near_pairs(vectors, 10).collect()
    assert sum(r.b in nearest[r.a] for r in found) >= 0.9 * 10 * len(ids) and len(found) <= 10 * len(ids)
    at = {int(i): k for k, i in enumerate(ids)}
    assert all(r.distance == pytest.approx(1 - score[at[r.a], at[r.b]]) for r in found[:200])


def test_louvain_by_joins_reaches_louvain_by_task(spark):
    from discourselab.workloads import _snapshots

    edges = _snapshots(spark, "/root/testdata/sf0.001", 0, "quarter", "1996-01-01", "1996-03-31", replies=True).cache()
    quality = lambda labels: community.modularity(edges, labels).first().modularity
    local = quality(community.louvain(edges))
    assert quality(community.louvain(edges, task_edges=10)) >= 0.97 * local
    assert quality(community.label_propagation(edges)) >= 0.6 * local


def test_clusters_of_the_most_excess_of_mass(spark):
    frame = lambda rows: spark.createDataFrame(rows, "node long, label long")
    a, b, c = range(0, 10), range(10, 20), range(20, 26)
    fine = frame([(i, 0) for i in a] + [(i, 10) for i in b])
    middle = frame([(i, 0) for i in a] + [(i, 10) for i in b] + [(i, 20) for i in c])
    coarse = frame([(i, 0) for i in (*a, *b, *c)])
    found = topics._excess_of_mass([fine, middle, coarse], [0.1, 0.5, 1.0], 5).collect()
    sets = {frozenset(r.node for r in found if r.cluster == name) for name in {r.cluster for r in found}}
    assert sets == {frozenset(a), frozenset(b), frozenset(c)}
    joined = frame([(i, 0) for i in (*a, *b)] + [(i, 20) for i in c])
    found = topics._excess_of_mass([fine, joined, coarse], [0.9, 1.0, 9.0], 5).collect()
    sets = {frozenset(r.node for r in found if r.cluster == name) for name in {r.cluster for r in found}}
    assert sets == {frozenset((*a, *b)), frozenset(c)}
    assert topics._excess_of_mass([fine], [0.5], 50) is None
