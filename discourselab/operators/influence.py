"""User similarity network, eigenvector centrality and influence, without ever writing the network.

The weight of two users is the sum over pairs of their posts and over topics of products of memberships.
That is bilinear, so it equals the dot product of two user profiles (sums of memberships by topic). A
product of the whole network with a vector needs one number per topic, which is what the driver holds.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from discourselab.session import cut, discard, freed_shuffles, scratch


def active_users(posts: DataFrame, min_posts: int = 10) -> DataFrame:
    """(user_id, n_posts, mean_score) of users with at least ``min_posts`` posts."""
    return (
        posts.groupBy(F.col("author_id").alias("user_id"))
        .agg(F.count("*").alias("n_posts"), F.avg("sentiment").alias("mean_score"))
        .where(F.col("n_posts") >= min_posts)
    )


def user_profiles(posts: DataFrame, members: DataFrame, users: DataFrame) -> DataFrame:
    """(user_id, topic_id, s): summed memberships of an active user's posts."""
    kept = posts.select("post_id", F.col("author_id").alias("user_id")).join(users.select("user_id"), "user_id", "left_semi")
    return kept.join(members, "post_id").groupBy("user_id", "topic_id").agg(F.sum("p").alias("s"))


def restrict(profiles: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, user_id, topic_id, s): profiles over the topics of each group."""
    return profiles.join(F.broadcast(groups), "topic_id").select("group_id", "user_id", "topic_id", "s")


def pair_weights(profiles: DataFrame, by: tuple[str, ...] = ("group_id",), cell: int = 20_000) -> DataFrame:
    """(by..., a, b, weight) of all pairs that share a topic: the whole network, as large as its pairs are many.

    Users are dealt to blocks of ``cell`` profile rows and more, and a task meets two blocks, so that all topics of a
    pair are summed where the pair is made: profiles are written once, pairs are never shuffled.
    """
    return _met(profiles.select(*by, F.col("user_id").alias("user"), F.col("user_id").alias("item"), "topic_id", F.col("s").alias("v")), by, cell)


def pair_weight_naive(posts: DataFrame, members: DataFrame, users: DataFrame, cell: int = 20_000) -> DataFrame:
    """(a, b, weight) by the sum over pairs of posts: the definition. Every pair of posts is computed in its users' blocks."""
    rows = posts.select("post_id", F.col("author_id").alias("user_id")).join(users, "user_id", "left_semi").join(members, "post_id")
    return _met(rows.select(F.col("user_id").alias("user"), F.col("post_id").alias("item"), "topic_id", F.col("p").alias("v")), (), cell)


#: Pairs of users, and of their items, that a task holds at once.
STRIP = 1_000_000
#: Pairs that a task makes where they are many: a file of some 130 MB.
PAIRS = 16_000_000
#: Tasks a core that small cells are joined down to, and small cells that one block may hold.
TASKS, CELLS = 6, 8


def _blocks(rows: int, users: int, kept: int, cell: int, cores: int) -> int:
    """Blocks for ``rows`` of ``users``, who stand ``kept`` times in groups: as few as give PAIRS a task and TASKS a core.

    A block has one to CELLS cells. Two blocks make a task, so tasks, and files, grow with the square of blocks.
    """
    small, large = -(-rows // cell), -(-rows // (cell * CELLS))
    by_pairs = math.ceil(math.sqrt(kept * users / PAIRS))
    by_cores = math.ceil((math.sqrt(1 + 8 * TASKS * cores) - 1) / 2)
    return max(1, min(small, max(large, by_pairs, by_cores)))


def _met(rows: DataFrame, by: tuple[str, ...], cell: int) -> DataFrame:
    """(by..., a, b, weight) from (by..., user, item, topic_id, v): the sum over pairs of items and over topics.

    Every block is one row of a written table. Tasks read two of its partitions, without a shuffle of either. What led to
    the blocks (shuffle files, the rows) is off the disk before pairs are made.
    """
    kinds, spark = dict(rows.dtypes), rows.sparkSession
    held = scratch(spark, "pairs-rows")
    with freed_shuffles(spark):
        rows.dropna(subset=[*by, "user", "topic_id"]).write.parquet(held)
        rows = spark.read.schema(rows.schema).parquet(held)
        known = rows.agg(F.count("*"), F.approx_count_distinct("user"), F.approx_count_distinct(F.struct(*by, "user"))).first()
        blocks = _blocks(*known, cell, spark.sparkContext.defaultParallelism)
        dealt = rows.withColumn("_block", F.pmod(F.xxhash64("user"), F.lit(blocks)).cast("int")).repartitionById(blocks, F.col("_block"))
        packed = cut(dealt.groupBy(*by, "_block").agg(F.collect_list(F.struct("user", "item", "topic_id", "v")).alias("rows")))
    discard(spark, held)
    left = packed.select(*by, F.col("_block").alias("i"), F.col("rows").alias("left"))
    right = packed.select(*(F.col(k).alias(f"_{k}") for k in by), F.col("_block").alias("j"), F.col("rows").alias("right"))
    together = F.col("i") <= F.col("j")
    for k in by:
        together &= F.col(k) == F.col(f"_{k}")
    schema = ", ".join([*(f"{k} {kinds[k]}" for k in by), f"a {kinds['user']}", f"b {kinds['user']}", "weight double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1)
                one, other = (_Block(row.column(side).flatten()) for side in ("left", "right"))
                same = row.column("i")[0].as_py() == row.column("j")[0].as_py()
                for a, b, weight in _weights(one, other, same):
                    keys = [pa.repeat(row.column(key)[0], len(weight)) for key in by]
                    yield pa.RecordBatch.from_arrays([*keys, a, b, weight], [*by, "a", "b", "weight"])

    return left.hint("shuffle_replicate_nl").join(right, together).select(*by, "i", "j", "left", "right").mapInArrow(run, schema)


class _Block:
    """Rows of some users, in order of user and item: ``users`` with the items of each, and rows by topic."""

    def __init__(self, rows: pa.StructArray) -> None:
        user, item, topic, v = pa.RecordBatch.from_struct_array(rows).sort_by([("user", "ascending"), ("item", "ascending")]).columns
        head = lambda x: np.flatnonzero(np.r_[True, pc.not_equal(x[1:], x[:-1]).to_numpy(zero_copy_only=False)])
        users = head(user)
        items = np.union1d(users, head(item))
        self.users = user.take(pa.array(users))
        self.first = np.searchsorted(items, users)
        self.row_item = np.searchsorted(items, np.arange(len(user)), side="right") - 1
        self.row_user = np.searchsorted(users, np.arange(len(user)), side="right") - 1
        self.item_user = self.row_user[items]
        self.topic, self.there = topic, v.is_valid().to_numpy(zero_copy_only=False)
        self.v = v.cast("double").fill_null(0.0).to_numpy()

    def dense(self, topics: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """By topic: values of items, whether there is one, and whether a user has a row, and one with a value."""
        at = pc.index_in(self.topic, value_set=topics)
        known = at.is_valid().to_numpy(zero_copy_only=False)
        column = at.fill_null(0).to_numpy()[known]
        items, users = np.zeros((len(self.item_user), len(topics))), np.zeros((2, len(self.users), len(topics)), "float32")
        np.add.at(items, (self.row_item[known], column), self.v[known])
        users[0, self.row_user[known], column] = 1
        valued = self.there[known]
        held = np.zeros(items.shape, bool)
        held[self.row_item[known][valued], column[valued]] = True
        users[1, self.row_user[known][valued], column[valued]] = 1
        return items, held, users[0], users[1]


def _weights(one: _Block, other: _Block, same: bool) -> Iterator[tuple[pa.Array, pa.Array, pa.Array]]:
    """(a, b, weight) of the pairs of two blocks' users, or of a block's own, that share a topic, strip by strip."""
    shared = pc.unique(one.topic)
    shared = shared.filter(pc.is_in(shared, value_set=pc.unique(other.topic)))
    (x, in_x, has_x, set_x), (y, in_y, has_y, set_y) = one.dense(shared), other.dense(shared)
    finite = bool(np.isfinite(x).all() and np.isfinite(y).all())
    right = np.arange(len(other.users))
    wide = max(1, STRIP // len(right))
    tall = max(1, STRIP // len(y))
    for low in range(0, len(one.users), wide):
        high = min(low + wide, len(one.users))
        ends = [*one.first[low:high], one.first[high] if high < len(one.first) else len(x)]
        weight = np.zeros((high - low, len(right)))
        for start in range(ends[0], ends[-1], tall):
            stop = min(start + tall, ends[-1])
            part = x[start:stop] @ y.T if finite else _by_topic(x[start:stop], y, in_x[start:stop], in_y)
            owner = one.item_user[start:stop] - low
            heads = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            if len(heads) < len(owner):
                part = np.add.reduceat(part, heads, axis=0)
            if len(other.first) < len(y):
                part = np.add.reduceat(part, other.first, axis=1)
            weight[owner[heads]] += part
        kept = has_x[low:high] @ has_y.T > 0
        if same:
            kept &= np.arange(low, high)[:, None] < right[None, :]
        a, b = np.nonzero(kept)
        empty = None if one.there.all() and other.there.all() else (set_x[low:high] @ set_y.T == 0)[a, b]
        names, others = one.users.take(pa.array(a + low)), other.users.take(pa.array(b))
        if not same:
            swapped = pc.greater(names, others)
            names, others = pc.if_else(swapped, others, names), pc.if_else(swapped, names, others)
        yield names, others, pa.array(weight[a, b], mask=empty)


def _by_topic(x: np.ndarray, y: np.ndarray, in_x: np.ndarray, in_y: np.ndarray) -> np.ndarray:
    """The product of items where values may be infinite or no number: topics that one lacks add nothing."""
    out = np.zeros((len(x), len(y)))
    for t in range(x.shape[1]):
        a, b = np.flatnonzero(in_x[:, t]), np.flatnonzero(in_y[:, t])
        with np.errstate(invalid="ignore"):
            out[np.ix_(a, b)] += np.outer(x[a, t], y[b, t])
    return out


def weighted_degree(profiles: DataFrame) -> DataFrame:
    """(group_id, user_id, degree): sum of a user's weights, from the total profile and no pairs."""
    total = profiles.groupBy("group_id", "topic_id").agg(F.sum("s").alias("t"))
    return (
        profiles.join(F.broadcast(total), ["group_id", "topic_id"])
        .groupBy("group_id", "user_id")
        .agg(F.sum(F.col("s") * (F.col("t") - F.col("s"))).alias("degree"))
    )


def _packed(profiles: DataFrame) -> DataFrame:
    """(group_id, user_id, s map, own): a user's profile in one row, and its weight with itself."""
    return (
        profiles.groupBy("group_id", "user_id")
        .agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("topic_id", "s")))).alias("s"), F.sum(F.col("s") * F.col("s")).alias("own"))
    )


#: Steps that are replayed from the topic vectors before the users' values are written.
REPLAY = 5


def eigen_centrality(profiles: DataFrame, tol: float = 1e-9, max_iter: int = 200, shift: float = 0.0) -> DataFrame:
    """(group_id, user_id, centrality): leading vector of the zero-diagonal weights, of unit length.

    The iterates of all users follow from the topic vectors, which are topics x groups numbers that the driver
    holds: a step is one aggregate over the packed profiles, and values are written every ``REPLAY`` steps.
    ``shift`` iterates W + shift x I, which settles weights whose pattern is bipartite (two users, a star).
    """
    return _Power(profiles, shift).run(max_iter, tol)


def eigen_centrality_steps(profiles: DataFrame, steps: int) -> DataFrame:
    """The same after a fixed number of steps."""
    return _Power(profiles, 0.0).run(steps, None)


class _Power:
    """Power iteration over packed profiles; ``past`` holds the steps since the users' values were written."""

    def __init__(self, profiles: DataFrame, shift: float) -> None:
        kinds = dict(profiles.dtypes)
        self.shift, self.group, self.topic = shift, kinds["group_id"], kinds["topic_id"]
        self.users = cut(_packed(profiles).withColumn("x", F.lit(1.0)))
        self.past: dict[object, list[tuple[dict, float]]] = {}

    def run(self, steps: int, tol: float | None) -> DataFrame:
        totals, _ = self._sums(None)
        for step in range(steps):
            sums, size = self._sums(totals)
            for g, now in size.items():
                norm = math.sqrt(now["yy"])
                self.past.setdefault(g, []).append((totals.get(g, {}), norm))
                totals[g] = {t: v / norm if norm else 0.0 for t, v in sums.get(g, {}).items()}
            if tol is not None and all(_settled(x["xy"], math.sqrt(x["yy"]), math.sqrt(x["xx"]), tol) for x in size.values()):
                break
            if step % REPLAY == REPLAY - 1:
                self.users, self.past = cut(self._now()), {}
        return self._now().select("group_id", "user_id", F.col("x").alias("centrality"))

    def _product(self, totals: Column, x: Column) -> Column:
        """What a step makes of a user's value before it is scaled."""
        sum_of = F.aggregate(F.map_entries("s"), F.lit(0.0), lambda a, e: a + e["value"] * F.coalesce(F.try_element_at(totals, e["key"]), F.lit(0.0)))
        return sum_of - F.col("own") * x + self.shift * x

    def _now(self) -> DataFrame:
        """The users' values after the steps that are not written yet."""
        if not self.past:
            return self.users
        kind = f"group_id {self.group}, steps array<struct<totals:map<{self.topic},double>,norm:double>>"
        steps = self.users.sparkSession.createDataFrame(list(self.past.items()), kind)
        moved = F.aggregate("steps", F.col("x"), lambda x, z: F.coalesce(F.try_divide(self._product(z["totals"], x), z["norm"]), F.lit(0.0)))
        return self.users.join(F.broadcast(steps), "group_id").withColumn("x", moved).drop("steps")

    def _sums(self, totals: dict | None) -> tuple[dict, dict]:
        """By group: sums by topic of profile times value, or with ``totals`` times the next product y, and of yy, xy, xx."""
        state = self._now()
        if totals is None:
            state = state.withColumn("y", F.col("x"))
        else:
            vectors = state.sparkSession.createDataFrame(list(totals.items()), f"group_id {self.group}, totals map<{self.topic},double>")
            state = state.join(F.broadcast(vectors), "group_id").withColumn("y", self._product(F.col("totals"), F.col("x")))
        part = lambda name, v, topic: F.struct(F.lit(name).alias("name"), topic.cast(self.topic).alias("topic_id"), v.alias("v"))
        x, y, none = F.col("x"), F.col("y"), F.lit(None)
        topics = F.transform(F.map_entries("s"), lambda e: part("t", e["value"] * y, e["key"]))
        sizes = F.array(part("yy", y * y, none), part("xy", x * y, none), part("xx", x * x, none))
        rows = state.select("group_id", F.inline(F.concat(topics, sizes))).groupBy("group_id", "name", "topic_id").agg(F.sum("v").alias("v")).collect()
        sums: dict = {}
        size: dict = {}
        for r in rows:
            if r.name == "t":
                sums.setdefault(r.group_id, {})[r.topic_id] = r.v
            else:
                size.setdefault(r.group_id, {})[r.name] = r.v
        return sums, size


def _settled(rayleigh: float, norm: float, length: float, tol: float) -> bool:
    """Is x an eigenvector? The angle between x and Wx, whose sine squared is 1 - cosine squared."""
    return norm == 0 or abs(length - 1) < 1e-6 and 1 - min(1.0, rayleigh / (norm * length)) ** 2 <= tol * tol + 1e-15


def _step(state: DataFrame, shift: float) -> DataFrame:
    totals = state.select("group_id", "x", F.explode("s").alias("topic_id", "v")).groupBy("group_id", "topic_id").agg(F.sum(F.col("v") * F.col("x")).alias("t"))
    vector = totals.groupBy("group_id").agg(F.map_from_entries(F.collect_list(F.struct("topic_id", "t"))).alias("t"))
    product = F.aggregate(F.map_entries("s"), F.lit(0.0), lambda a, e: a + e["value"] * F.coalesce(F.try_element_at("t", e["key"]), F.lit(0.0)))
    return state.join(F.broadcast(vector), "group_id").withColumn("y", product - F.col("own") * F.col("x") + shift * F.col("x")).drop("t")


def eigen_centrality_edges(edges: DataFrame, steps: int = 50, shift: float = 1.0) -> DataFrame:
    """(node, centrality) of a general undirected (src, dst, weight) edge table by power iteration."""
    both = cut(edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")))
    state = cut(both.select(F.col("src").alias("node")).distinct().withColumn("x", F.lit(1.0)))
    for _ in range(steps):
        moved = both.join(state, both.dst == state.node).groupBy("src").agg(F.sum(F.col("weight") * F.col("x")).alias("y"))
        y = state.join(moved, state.node == moved.src, "left").select("node", (F.coalesce("y", F.lit(0.0)) + shift * F.col("x")).alias("y"))
        norm = y.agg(F.sqrt(F.sum(F.col("y") * F.col("y"))).alias("norm"))
        state = cut(y.crossJoin(F.broadcast(norm)).select("node", F.coalesce(F.try_divide("y", "norm"), F.lit(0.0)).alias("x")))
    return state.select("node", F.col("x").alias("centrality"))


def eigen_dense(weights: np.ndarray) -> np.ndarray:
    """Leading eigenvector of a dense symmetric matrix, for checks."""
    values, vectors = np.linalg.eigh(weights)
    return np.abs(vectors[:, np.argmax(values)])


def eigen_residual(profiles: DataFrame, centrality: DataFrame) -> DataFrame:
    """(group_id, residual): |Wc - lambda c| / lambda of a unit vector c."""
    state = _step(_packed(profiles).join(centrality.withColumnRenamed("centrality", "x"), ["group_id", "user_id"]), 0.0)
    held = state.groupBy("group_id").agg(F.sum(F.col("x") * F.col("y")).alias("l"), F.sum(F.col("y") * F.col("y")).alias("y2"))
    return (
        held.select("group_id", F.sqrt(F.greatest(F.lit(0.0), F.col("y2") - F.col("l") * F.col("l"))).alias("d"), "l")
        .select("group_id", F.try_divide("d", "l").alias("residual"))
    )


def influence_score(centrality: Column, followers: Column) -> Column:
    return centrality * F.ln(followers + 1.0)


def influence(centrality: DataFrame, users: DataFrame, followers: DataFrame) -> DataFrame:
    """(group_id, user_id, centrality, followers, n_posts, score, influence)."""
    return (
        centrality.join(users, "user_id")
        .join(followers, "user_id")
        .select(
            "group_id",
            "user_id",
            "centrality",
            "followers",
            "n_posts",
            F.col("mean_score").alias("score"),
            influence_score(F.col("centrality"), F.col("followers")).alias("influence"),
        )
    )


def top_influencers(scored: DataFrame, k: int = 5, anonymise: bool = True) -> DataFrame:
    """The ``k`` most influential users of each group; ids are withheld unless asked for."""
    order = Window.partitionBy("group_id").orderBy(F.desc(F.round("influence", 9)), "user_id")
    top = scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return top.drop("user_id") if anonymise else top


def influence_by_sentiment(scored: DataFrame, width: float = 0.1, min_users: int = 10) -> DataFrame:
    """(group_id, bin_lo, n, mean, se, is_peak) of users by sentiment interval; small bins are dropped."""
    scale = round(1 / width)
    bins = scored.withColumn("_b", F.floor(F.round(F.col("score") * scale, 9)))
    held = (
        bins.groupBy("group_id", "_b")
        .agg(F.count("*").alias("n"), F.avg("influence").alias("mean"), (F.stddev_samp("influence") / F.sqrt(F.count("*"))).alias("se"))
        .where(F.col("n") >= min_users)
    )
    first = F.row_number().over(Window.partitionBy("group_id").orderBy(F.desc(F.round("mean", 9)), "_b"))
    return held.select("group_id", (F.col("_b") / scale).alias("bin_lo"), "n", "mean", "se", (first == 1).alias("is_peak"))


def bin_error_contrast(bins: DataFrame) -> DataFrame:
    return bins.groupBy("group_id").agg(F.avg("se").alias("mean_se"))


def group_contrast(top: DataFrame) -> DataFrame:
    """(group_id, mean_centrality, mean_followers, mean_posts, mean_score, mean_influence) of top users."""
    means = {"mean_centrality": "centrality", "mean_followers": "followers", "mean_posts": "n_posts", "mean_score": "score", "mean_influence": "influence"}
    return top.groupBy("group_id").agg(*(F.avg(c).alias(name) for name, c in means.items()))


def rank_by(scored: DataFrame, column: str, k: int = 5) -> DataFrame:
    order = Window.partitionBy("group_id").orderBy(F.desc(column), "user_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("group_id", "user_id", "rank")


def overlap_at(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """(group_id, overlap): share of the first k of one ranking that is among the first k of another."""
    both = a.where(F.col("rank") <= k).join(b.where(F.col("rank") <= k).select("group_id", "user_id", F.lit(1).alias("hit")), ["group_id", "user_id"], "left")
    return both.groupBy("group_id").agg((F.coalesce(F.sum("hit"), F.lit(0)) / k).alias("overlap"))


def printed_influence(centrality: float, followers: int) -> float:
    return centrality * math.log(followers + 1)
