"""The Louvain chain over all months against brute force in plain Python."""

from collections import defaultdict

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as driver
from discourselab import chains
from discourselab.operators.community import louvain_labels
from discourselab.sources import carriers as cv


@pytest.fixture(scope="module")
def tables():
    """Large enough for communities in most months."""
    return "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def found(spark, tables):
    """{(group, month): {community: users}} from posts and memberships, without the operators' joins."""
    topics = defaultdict(set)
    for r in cv.topic_groups(spark).collect():
        topics[r.group_id].add(r.topic_id)
    posts = {r.post_id: r for r in cv.posts_retail(spark, tables).collect()}
    edges = defaultdict(lambda: defaultdict(float))
    orders = defaultdict(list)
    for r in sorted(spark.read.parquet(f"{tables}/orders.parquet").collect(), key=lambda r: r.o_orderkey):
        orders[r.o_orderdate, r.o_orderpriority].append(r)
    answers = {b.o_orderkey: a.o_custkey for held in orders.values() for a, b in zip(held, held[1:], strict=False) if a.o_custkey != b.o_custkey}
    for m in cv.membership_retail(spark, tables).collect():
        if (post := posts.get(m.post_id)) and cv.PERIOD[0] <= str(post.day) <= cv.PERIOD[1]:
            for g in cv.FOCAL:
                if m.topic_id in topics[g]:
                    own = edges[g, post.month]
                    if (f"post:{m.post_id}", f"user:{post.author_id}") not in own and m.post_id in answers:
                        own[tuple(sorted((f"user:{post.author_id}", f"user:{answers[m.post_id]}")))] += 1.0
                    own[f"post:{m.post_id}", f"user:{post.author_id}"] = 1.0
                    own[f"post:{m.post_id}", f"topic:{m.topic_id}"] = 1.0
    out = {}
    for (g, month), held in edges.items():
        sets = defaultdict(set)
        for node, label in louvain_labels(sorted((*e, w) for e, w in held.items())).items():
            if node.startswith("user:"):
                sets[f"{g}|{label}"].add(int(node[5:]))
        out[g, month] = {c: u for c, u in sets.items() if len(u) >= chains.FLOORS[g]}
    return out


@pytest.fixture(scope="module")
def links(found):
    out = {}
    for (g, month), sets in found.items():
        after = found.get((g, later(month)), {})
        for a, u in sets.items():
            for b, v in after.items():
                if u & v and len(u & v) / len(u | v) >= chains.GAMMA:
                    out[g, month, a, b] = (len(u & v), round(len(u & v) / len(u | v), 6))
    return out


def later(month):
    return month.replace(year=month.year + month.month // 12, month=month.month % 12 + 1)


def run(spark, tables, name):
    return driver.queries()[name](spark, tables).collect()


def test_communities_of_all_months(spark, tables, found):
    """Nodes move in the order of their names, so that the order of edges changes nothing."""
    sets = defaultdict(set)
    for r in chains.communities(spark, tables).collect():
        sets[r.group_id, r.period, r.community].add(r.user_id)
    assert {k: u for k, u in sets.items()} == {(g, m, c): u for (g, m), s in found.items() for c, u in s.items()}
    assert len({m for g, m, _ in sets}) > 60


def test_links(spark, tables, links):
    rows = run(spark, tables, "w39c_louvain_links")
    assert links and {(r.group_id, r.period, r.a, r.b): (r.common, r.jaccard) for r in rows} == links


def test_evolution(spark, tables, found, links):
    after, before = defaultdict(int), defaultdict(int)
    for g, month, a, b in links:
        after[g, month, a] += 1
        before[g, later(month), b] += 1
    keys = [(g, m, c) for (g, m), s in found.items() for c in s]
    first, last = min(k[1] for k in keys), max(k[1] for k in keys)
    expected = set()
    for k in keys:
        x, y = before[k], after[k]
        expected |= {(*k, e) for e, holds in (("birth", x == 0 and k[1] > first), ("death", y == 0 and k[1] < last), ("split", y > 1), ("merge", x > 1), ("continue", x <= 1 and y == 1)) if holds}
    rows = run(spark, tables, "w40c_louvain_evolution")
    assert len(rows) == len(expected) and {(r.group_id, r.period, r.community, r.event) for r in rows} == expected


def test_lifespans(spark, tables, found, links):
    length = {}
    for (g, month), sets in sorted(found.items()):
        for c in sets:
            length[month, c] = 1 + max((length[m, a] for h, m, a, b in links if b == c and later(m) == month), default=0)
    rows = run(spark, tables, "w40d_louvain_lifespans")
    assert {(r.period, r.community): r.length for r in rows} == length and max(length.values()) > 1


def test_sentiment(spark, tables, found):
    scores = {r.author_id: r.s for r in cv.posts_retail(spark, tables).groupBy("author_id").agg(F.avg("sentiment").alias("s")).collect()}
    rows = {(r.group_id, r.period, r.community): (r["size"], r.mean_score) for r in run(spark, tables, "w41b_louvain_sentiment")}
    assert len(rows) == sum(map(len, found.values()))
    for (g, month), sets in found.items():
        for c, users in sets.items():
            size, mean = rows[g, month, c]
            assert size == len(users) and mean == pytest.approx(sum(scores[u] for u in users) / size, abs=2e-6)
