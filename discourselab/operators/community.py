"""Communities of users: periodic snapshots, Louvain, modularity, and how communities evolve."""

from __future__ import annotations

from collections import defaultdict

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from discourselab.plans.iterate import components
from discourselab.session import cut, settle


def snapshots(
    posts: DataFrame,
    members: DataFrame,
    topics: DataFrame,
    period: str = "month",
    weight_mode: str = "unit",
    replies: DataFrame | None = None,
) -> DataFrame:
    """(period, src, dst, weight): undirected edges of a group by month, quarter or week.

    A post's edges are user-post and post-topic; memberships weigh one each, or their probability. With
    (post_id, src_user, dst_user, day) replies, users are linked by the group's posts that answer another.
    """
    at = F.to_date(F.date_trunc(period, "day")).alias("period")
    inside = members.join(F.broadcast(topics), "topic_id", "left_semi").join(posts, "post_id")
    post = F.concat(F.lit("post:"), F.col("post_id").cast("string"))
    written = (
        inside.select(at, F.concat(F.lit("user:"), F.col("author_id").cast("string")).alias("a"), post.alias("b"))
        .distinct()
        .withColumn("weight", F.lit(1.0))
    )
    about = inside.select(
        at,
        post.alias("a"),
        F.concat(F.lit("topic:"), F.col("topic_id").cast("string")).alias("b"),
        (F.lit(1.0) if weight_mode == "unit" else F.col("p")).alias("weight"),
    )
    edges = written.unionByName(about)
    if replies is not None:
        user = lambda c: F.concat(F.lit("user:"), F.col(c).cast("string"))
        answers = replies.join(inside.select("post_id").distinct(), "post_id", "left_semi")
        edges = edges.unionByName(answers.select(at, user("src_user").alias("a"), user("dst_user").alias("b"), F.lit(1.0).alias("weight")))
    return edges.groupBy("period", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("weight").alias("weight"))


def _gain_pass(neighbours: list[dict[int, float]], own: list[float], total: float, resolution: float) -> list[int]:
    """Local moves of one level, in node order, until none improves modularity."""
    n = len(neighbours)
    label, degree = list(range(n)), [sum(x.values()) + 2 * own[i] for i, x in enumerate(neighbours)]
    held = degree.copy()
    moved = True
    while moved:
        moved = False
        for i in range(n):
            here = label[i]
            held[here] -= degree[i]
            to: dict[int, float] = defaultdict(float)
            for j, w in neighbours[i].items():
                to[label[j]] += w
            value = lambda c, i=i, to=to: to.get(c, 0.0) - resolution * degree[i] * held[c] / total
            best, most = here, value(here)
            for c in sorted(to):
                if (v := value(c)) > most + 1e-12:
                    best, most = c, v
            held[best] += degree[i]
            if best != here:
                label[i], moved = best, True
    return label


def louvain_labels(edges: list[tuple[str, str, float]], resolution: float = 1.0) -> dict[str, str]:
    """Label of every node of one graph that fits one task; the label is the smallest node of a community."""
    names = sorted({x for a, b, _ in edges for x in (a, b)})
    number = {x: i for i, x in enumerate(names)}
    neighbours: list[dict[int, float]] = [defaultdict(float) for _ in names]
    own = [0.0] * len(names)
    for a, b, w in edges:
        i, j = number[a], number[b]
        if i == j:
            own[i] += w
        else:
            neighbours[i][j] += w
            neighbours[j][i] += w
    total = sum(sum(x.values()) for x in neighbours) + 2 * sum(own)
    member = list(range(len(names)))
    while total > 0:
        label = _gain_pass(neighbours, own, total, resolution)
        kinds = {c: k for k, c in enumerate(sorted(set(label)))}
        if len(kinds) == len(neighbours):
            break
        member = [kinds[label[m]] for m in member]
        merged: list[dict[int, float]] = [defaultdict(float) for _ in kinds]
        inner = [0.0] * len(kinds)
        for i, row in enumerate(neighbours):
            a = kinds[label[i]]
            inner[a] += own[i]
            for j, w in row.items():
                b = kinds[label[j]]
                if a == b:
                    inner[a] += w / 2
                else:
                    merged[a][b] += w
        neighbours, own = merged, inner
    first: dict[int, str] = {}
    for name, m in zip(names, member, strict=True):
        first.setdefault(m, name)
    return {name: first[m] for name, m in zip(names, member, strict=True)}


def louvain(edges: DataFrame, resolution: float = 1.0, task_edges: int = 2_000_000) -> DataFrame:
    """(period, node, community): Louvain of each snapshot, one task a snapshot.

    Snapshots of more than ``task_edges`` edges go through the joins of ``louvain_distributed``.
    """

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = louvain_labels(list(rows[["src", "dst", "weight"]].itertuples(index=False, name=None)), resolution)
        return pd.DataFrame({"period": key[0], "node": list(found), "community": list(found.values())})

    edges = cut(edges)
    large = [r.period for r in edges.groupBy("period").agg(F.count("*").alias("n")).where(F.col("n") > task_edges).collect()]
    inside = F.col("period").isin(*large) if large else F.lit(False)
    local = edges.where(~inside).groupBy("period").applyInPandas(run, "period date, node string, community string")
    return local.unionByName(louvain_distributed(edges.where(inside), resolution)) if large else local


def modularity(edges: DataFrame, labels: DataFrame, resolution: float = 1.0) -> DataFrame:
    """(period, modularity) of a labelling of undirected weighted snapshots. Labels, as many as nodes, are not broadcast."""
    named = labels.select("period", F.col("node"), F.col("community")).hint("merge")
    both = (
        edges.join(named.withColumnsRenamed({"node": "src", "community": "c1"}), ["period", "src"])
        .join(named.withColumnsRenamed({"node": "dst", "community": "c2"}), ["period", "dst"])
    )
    inside = both.groupBy("period").agg(F.sum("weight").alias("m"), F.sum(F.when(F.col("c1") == F.col("c2"), F.col("weight")).otherwise(0.0)).alias("inside"))
    ends = both.select("period", F.explode(F.array("c1", "c2")).alias("community"), "weight").groupBy("period", "community").agg(F.sum("weight").alias("d"))
    square = ends.groupBy("period").agg(F.sum(F.col("d") * F.col("d")).alias("d2"))
    return (
        inside.join(square, "period")
        .select("period", (F.col("inside") / F.col("m") - resolution * F.col("d2") / (4 * F.col("m") * F.col("m"))).alias("modularity"))
    )


def louvain_distributed(edges: DataFrame, resolution: float = 1.0, tol: float = 1e-4, max_rounds: int = 100) -> DataFrame:
    """(period, node, community) by Louvain over joins, for snapshots of any size.

    In a round every node prices the communities around it, and those of one half of the nodes (by a hash of
    node and round) move to the one of the largest gain; the other half stays, which keeps neighbours from
    trading places. A level ends when no node gains by a move, or when three rounds have not raised the
    modularity by ``tol``; the labels of its best round count. Communities then contract to nodes, until a
    level merges none. A round is one table and one row for the driver.
    """
    pair = [F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")]
    graph = settle(edges.groupBy("period", *pair).agg(F.sum("weight").cast("double").alias("weight")))
    final = graph.select("period", F.explode(F.array("src", "dst")).alias("node")).distinct().withColumn("community", F.col("node"))
    while True:
        nodes, labels = _level(graph, resolution, tol, max_rounds)
        if labels.select("period", "own").distinct().count() == nodes:
            return final
        named = labels.withColumn("name", F.min("node").over(Window.partitionBy("period", "own"))).select("period", "node", "name")
        named = settle(named)
        final = settle(
            final.join(named.withColumnRenamed("node", "community"), ["period", "community"]).select("period", "node", F.col("name").alias("community"))
        )
        ends = [named.withColumnsRenamed({"node": end, "name": new}) for end, new in (("src", "a"), ("dst", "b"))]
        moved = graph.join(ends[0], ["period", "src"]).join(ends[1], ["period", "dst"])
        graph = settle(moved.groupBy("period", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("weight").alias("weight")))


def _level(graph: DataFrame, resolution: float, tol: float, max_rounds: int) -> tuple[int, DataFrame]:
    """How many nodes a graph has, and their labels (period, node, own) once moves no longer pay."""
    both = settle(_both_ways(graph.where("src <> dst")))
    ends = graph.select("period", F.explode(F.array("src", "dst")).alias("node"), "weight")
    labels = settle(ends.groupBy("period", "node").agg(F.sum("weight").alias("k")).withColumn("own", F.col("node")))
    total = settle(labels.groupBy("period").agg(F.sum("k").alias("m2")))
    best, most, idle = labels, None, 0
    for turn in range(max_rounds):
        size = labels.groupBy("period", F.col("own").alias("community")).agg(F.sum("k").alias("held"))
        to = both.join(labels.select("period", F.col("node").alias("dst"), F.col("own").alias("community")), ["period", "dst"])
        around = to.select("period", F.col("src").alias("node"), "community", "weight")
        staying = labels.select("period", "node", F.col("own").alias("community"), F.lit(0.0).alias("weight"))
        options = around.unionByName(staying).groupBy("period", "node", "community").agg(F.sum("weight").alias("w"))
        priced = options.join(size, ["period", "community"]).join(labels, ["period", "node"]).join(F.broadcast(total), "period")
        home = F.col("community") == F.col("own")
        others = F.col("held") - F.when(home, F.col("k")).otherwise(0.0)
        gain = F.round(F.col("w") - resolution * F.col("k") * others / F.col("m2"), 12)
        first = F.struct(-gain, (~home).cast("int"), "community")
        inside = F.max(F.when(home, F.col("w")))
        wanted = priced.groupBy("period", "node", "own", "k", "m2").agg(F.min_by("community", first).alias("target"), inside.alias("inside"))
        wanted = settle(wanted)
        share = F.sum("inside") / F.first("m2") - resolution * F.pow(F.sum("k") / F.first("m2"), F.lit(2))
        groups = wanted.groupBy("period", "own").agg(share.alias("share"), F.count(F.when(F.col("target") != F.col("own"), 1)).alias("movers"))
        now = groups.agg(F.sum("share").alias("quality"), F.sum("movers").alias("movers")).first()
        if most is None or now.quality > most + tol:
            best, most, idle = wanted, now.quality, 0
        else:
            idle += 1
        if not now.movers or idle == 3:
            break
        may = F.pmod(F.xxhash64("node", F.lit(turn)), F.lit(2)) == 0
        labels = wanted.select("period", "node", "k", F.when(may, F.col("target")).otherwise(F.col("own")).alias("own"))
    return best.count(), best.select("period", "node", "own")


def _both_ways(edges: DataFrame) -> DataFrame:
    back = edges.select("period", F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")
    return edges.select("period", "src", "dst", "weight").unionByName(back)


def label_propagation(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(period, node, community): nodes take the heaviest label around them until none wants another.

    A node keeps its label if that is among the heaviest, else the smallest of those wins. In a round half
    of the nodes may move, by a hash of node and round: were all to move at once, the two sides of a
    bipartite snapshot would trade labels for ever.
    """
    both = cut(_both_ways(edges))
    labels = both.select("period", F.col("src").alias("node")).distinct().withColumn("community", F.col("node"))
    for turn in range(max_rounds):
        around = (
            both.join(labels.withColumnRenamed("node", "dst").hint("merge"), ["period", "dst"])
            .groupBy("period", F.col("src").alias("node"), "community")
            .agg(F.round(F.sum("weight"), 9).alias("w"))
        )
        own = labels.withColumnRenamed("community", "own")
        order = F.struct(-F.col("w"), (F.col("community") != F.col("own")).cast("int"), "community")
        wanted = cut(around.join(own.hint("merge"), ["period", "node"]).groupBy("period", "node", "own").agg(F.min_by("community", order).alias("community")))
        if wanted.where("community <> own").isEmpty():
            return settle(wanted.select("period", "node", "community"))
        may = F.pmod(F.xxhash64("node", F.lit(turn)), F.lit(2)) == 0
        labels = wanted.select("period", "node", F.when(may, F.col("community")).otherwise(F.col("own")).alias("community"))
    raise RuntimeError(f"labels still move after {max_rounds} rounds")


def period_components(edges: DataFrame) -> DataFrame:
    """(period, node, label): connected components of every snapshot at once."""
    tag = lambda c: F.concat(F.date_format("period", "yyyy-MM-dd"), F.lit("|"), F.col(c))
    found = components(edges.select(tag("src").alias("src"), tag("dst").alias("dst")))
    return found.select(
        F.to_date(F.substring_index("node", "|", 1)).alias("period"),
        F.substring_index("node", "|", -1).alias("node"),
        F.substring_index("label", "|", -1).alias("label"),
    )


def user_communities(labels: DataFrame, min_size: int) -> DataFrame:
    """(period, community, user_id) of communities with at least ``min_size`` users; other nodes are dropped."""
    users = labels.where(F.col("node").startswith("user:")).select("period", "community", F.substring_index("node", ":", -1).cast("long").alias("user_id"))
    return floor_size(users, ["period"], min_size)


def floor_size(users: DataFrame, by: list[str], min_size: int) -> DataFrame:
    size = F.count("*").over(Window.partitionBy(*by, "community"))
    return users.withColumn("_n", size).where(F.col("_n") >= min_size).drop("_n")


def evolve(users: DataFrame, step_months: int, gamma: float = 0.01, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., period, a, b, common, jaccard) of communities of a period and the next one.

    An inverted index on users: only communities that share one meet.
    """
    sizes = users.groupBy(*by, "period", "community").agg(F.count("*").alias("size"))
    now = users.select(*by, "period", F.col("community").alias("a"), "user_id", F.add_months("period", step_months).alias("_next"))
    later = users.select(*by, F.col("period").alias("_next"), F.col("community").alias("b"), "user_id")
    common = now.join(later, [*by, "_next", "user_id"]).groupBy(*by, "period", "_next", "a", "b").agg(F.count("*").alias("common"))
    first = sizes.select(*by, "period", F.col("community").alias("a"), F.col("size").alias("_sa"))
    second = sizes.select(*by, F.col("period").alias("_next"), F.col("community").alias("b"), F.col("size").alias("_sb"))
    linked = common.join(first, [*by, "period", "a"]).join(second, [*by, "_next", "b"])
    return (
        linked.select(*by, "period", "a", "b", "common", (F.col("common") / (F.col("_sa") + F.col("_sb") - F.col("common"))).alias("jaccard"))
        .where(F.col("jaccard") >= gamma)
    )


def evolve_bruteforce(users: DataFrame, step_months: int, gamma: float = 0.01) -> DataFrame:
    """The same by comparing all pairs of user sets: a baseline for small tables."""
    sets = users.groupBy("period", "community").agg(F.collect_set("user_id").alias("s"))
    later = sets.select(F.col("period").alias("_p"), F.col("community").alias("b"), F.col("s").alias("t"))
    pairs = sets.withColumnRenamed("community", "a").join(later, F.add_months("period", step_months) == F.col("_p"))
    common, union = F.size(F.array_intersect("s", "t")), F.size(F.array_union("s", "t"))
    return pairs.select("period", "a", "b", common.cast("long").alias("common"), (common / union).alias("jaccard")).where(F.col("jaccard") >= gamma)


def classify_evolution(users: DataFrame, links: DataFrame, step_months: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., period, community, event) of birth, death, split, merge and continue; a community may have two."""
    nodes = users.select(*by, "period", "community").distinct()
    out = links.groupBy(*by, "period", F.col("a").alias("community")).agg(F.count("*").alias("after"))
    back = links.groupBy(*by, F.add_months("period", step_months).alias("period"), F.col("b").alias("community")).agg(F.count("*").alias("before"))
    keys = [*by, "period", "community"]
    held = nodes.join(out, keys, "left").join(back, keys, "left").fillna(0, ["after", "before"])
    last, first = (nodes.agg(f("period")).first()[0] for f in (F.max, F.min))
    events = F.array(
        F.when((F.col("before") == 0) & (F.col("period") > F.lit(first)), "birth"),
        F.when((F.col("after") == 0) & (F.col("period") < F.lit(last)), "death"),
        F.when(F.col("after") > 1, "split"),
        F.when(F.col("before") > 1, "merge"),
        F.when((F.col("before") <= 1) & (F.col("after") == 1), "continue"),
    )
    return held.select(*keys, F.explode(F.array_compact(events)).alias("event"))


def lifespans(users: DataFrame, links: DataFrame, step_months: int, max_periods: int = 240) -> DataFrame:
    """(period, community, length): periods in the longest chain of links that ends at a community."""
    now = cut(users.select("period", "community").distinct().withColumn("length", F.lit(1)))
    for _ in range(max_periods):
        carried = (
            links.join(now.withColumnRenamed("community", "a"), ["period", "a"])
            .groupBy(F.add_months("period", step_months).alias("period"), F.col("b").alias("community"))
            .agg((F.max("length") + 1).alias("longer"))
        )
        better = cut(now.join(carried, ["period", "community"], "left").select("period", "community", F.greatest("length", "longer").alias("length")))
        if better.exceptAll(now).isEmpty():
            break
        now = better
    return now


def community_nodes(users: DataFrame, scores: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., period, community, size, mean_score): users, and the mean of their mean scores."""
    return users.join(scores, "user_id", "left").groupBy(*by, "period", "community").agg(F.count("*").alias("size"), F.avg("mean_score").alias("mean_score"))
