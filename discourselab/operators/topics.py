"""Topics: embedding, reduction, clustering with an outlier class, soft membership, description, groups."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import IDF, PCA, HashingTF, Normalizer, Tokenizer, Word2Vec
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from discourselab.functions.text import clean_text, ngrams
from discourselab.plans.iterate import components
from discourselab.session import cut, prepare

OUTLIER = -1
#: Vectors that fit the cells of a neighbour search, those of them that measure it, and rows of a part of a cell.
SAMPLE, PROBES, CELL_ROWS = 4096, 256, 4096


def embed(docs: DataFrame, key: str, text: str, method: str = "hash", size: int = 64) -> DataFrame:
    """(vec_id, embedding): unit vectors by hashed term frequencies, or by mean word vectors."""
    words = Tokenizer(inputCol="_clean", outputCol="_words").transform(
        docs.select(F.col(key).alias("vec_id"), clean_text(F.coalesce(F.col(text), F.lit(""))).alias("_clean"))
    )
    if method == "w2v":
        made = Word2Vec(vectorSize=size, minCount=2, seed=1, inputCol="_words", outputCol="_raw").fit(words).transform(words)
    else:
        counted = HashingTF(numFeatures=size, inputCol="_words", outputCol="_tf").transform(words)
        made = IDF(inputCol="_tf", outputCol="_raw").fit(counted).transform(counted)
    return Normalizer(inputCol="_raw", outputCol="_unit").transform(made).select("vec_id", vector_to_array("_unit", "float32").alias("embedding"))


def reduce_dimensions(vectors: DataFrame, k: int = 10, method: str = "pca", seed: int = 1) -> DataFrame:
    """(vec_id, embedding) in ``k`` dimensions, by principal components or a random projection."""
    if method == "pca":
        dense = vectors.select("vec_id", array_to_vector("embedding").alias("v"))
        return PCA(k=k, inputCol="v", outputCol="r").fit(dense).transform(dense).select("vec_id", vector_to_array("r", "float32").alias("embedding"))
    d = vectors.select(F.size("embedding")).first()
    plane = np.random.default_rng(seed).normal(size=(k, d[0] if d else 0)) / np.sqrt(k)
    rows = [F.aggregate(F.zip_with("embedding", F.array(*map(F.lit, row.tolist())), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x) for row in plane]
    return vectors.select("vec_id", F.array(*(r.cast("float") for r in rows)).alias("embedding"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def plant(vectors: DataFrame, label: str, strength: float) -> DataFrame:
    """Blend a unit axis for each label into the vectors: a positive control with known clusters."""
    raised = F.transform("embedding", lambda x, i: x.cast("double") + F.when(i == F.col(label), strength).otherwise(0.0))
    held = vectors.withColumn("_v", raised)
    return held.withColumn("embedding", F.transform("_v", lambda x: (x / F.sqrt(dot(F.col("_v"), F.col("_v")))).cast("float"))).drop("_v")


def cluster_centroid(vectors: DataFrame, k: int, min_topic_size: int = 30, radius: float | None = None, seed: int = 1) -> DataFrame:
    """(vec_id, topic_id) by cosine k-means; vectors beyond ``radius`` and small clusters are outliers."""
    dense = vectors.select("vec_id", array_to_vector("embedding").alias("features"))
    model = KMeans(k=k, seed=seed, distanceMeasure="cosine").fit(dense)
    assigned = model.transform(dense).select("vec_id", F.col("prediction").alias("topic_id"), vector_to_array("features").alias("v"))
    if radius is not None:
        centers = vectors.sparkSession.createDataFrame(
            [(k, [float(x) for x in c]) for k, c in enumerate(model.clusterCenters())],
            "topic_id int, c array<double>",
        )
        cosine = dot(F.col("v"), F.col("c")) / F.sqrt(dot(F.col("v"), F.col("v")) * dot(F.col("c"), F.col("c")))
        assigned = assigned.join(F.broadcast(centers), "topic_id").withColumn("topic_id", F.when(1 - cosine <= radius, F.col("topic_id")).otherwise(OUTLIER))
    sizes = assigned.groupBy("topic_id").agg(F.count("*").alias("size"))
    return (
        assigned.join(F.broadcast(sizes), "topic_id")
        .select("vec_id", F.when(F.col("size") >= min_topic_size, F.col("topic_id")).otherwise(OUTLIER).cast("int").alias("topic_id"))
    )


def _cell_centers(sample: np.ndarray, count: int, seed: int) -> np.ndarray:
    """Unit centers of some cells by a few rounds of cosine k-means on a bounded sample."""
    held = sample[np.random.default_rng(seed).choice(len(sample), count, replace=False)]
    for _ in range(8):
        home = np.argmax(sample @ held.T, axis=1)
        sums = np.zeros_like(held)
        np.add.at(sums, home, sample)
        size = np.linalg.norm(sums, axis=1, keepdims=True)
        held = np.where(size > 0, sums / np.maximum(size, 1e-12), held)
    return held


def _unit(column: pa.Array) -> np.ndarray:
    rows = np.array(column.to_pylist(), np.float64).reshape(len(column), -1)
    return rows / np.maximum(np.linalg.norm(rows, axis=1, keepdims=True), 1e-12)


def _nearest(score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the k largest scores of every row."""
    if score.shape[1] > k:
        top = np.argpartition(-score, k - 1, axis=1)[:, :k]
    else:
        top = np.broadcast_to(np.arange(score.shape[1]), score.shape)
    return np.repeat(np.arange(len(score)), top.shape[1]), top.ravel()


def _cells_to_visit(vectors: DataFrame, probes: np.ndarray, ids: list, held: np.ndarray, k: int, least_recall: float) -> int:
    """In how many of its nearest cells a vector has to look, by the true neighbours of some probes."""
    spread = vectors.sparkSession.sparkContext.broadcast((probes, held))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        queries, cells = spread.value
        rank = np.argsort(np.argsort(-(queries @ cells.T), axis=1), axis=1)
        for batch in batches:
            rows = _unit(batch.column(1))
            score = queries @ rows.T
            q, b = _nearest(score, k + 1)
            home = np.argmax(rows @ cells.T, axis=1)
            columns = [pa.array(q), batch.column(0).take(pa.array(b)), pa.array(score[q, b]), pa.array(rank[q, home[b]])]
            yield pa.RecordBatch.from_arrays(columns, ["q", "b", "score", "rank"])

    found = vectors.select("vec_id", "embedding").mapInArrow(run, "q long, b long, score double, rank long")
    own = vectors.sparkSession.createDataFrame(list(enumerate(ids)), "q long, b long")
    others = found.join(F.broadcast(own), ["q", "b"], "left_anti")
    first = F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), "b"))
    ranks = sorted(r.rank for r in others.withColumn("_r", first).where(F.col("_r") <= k).collect())
    return ranks[min(len(ranks) - 1, int(np.ceil(least_recall * len(ranks))) - 1)] + 1 if ranks else 1


def near_pairs(vectors: DataFrame, k: int = 10, least_recall: float = 0.97, seed: int = 3) -> DataFrame:
    """(a, b, distance): about the ``k`` nearest neighbours by cosine of every (vec_id, embedding) row.

    Vectors live in the cell of their nearest center (about the square root of their number, fitted on
    ``SAMPLE`` of them) and look in as many of their nearest cells as it takes for ``PROBES`` of them to find
    ``least_recall`` of their true neighbours: few where the vectors cluster, most where they are noise. Large
    cells are split, and every visitor sees all parts.
    """
    spark = prepare(vectors.sparkSession)
    rows = cut(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding"))
    n = rows.count()
    drawn = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).collect()
    if n < 2:
        return rows.select(F.col("vec_id").alias("a"), F.col("vec_id").alias("b"), F.lit(0.0).alias("distance")).limit(0)
    sample = _unit(pa.array([r.embedding for r in drawn]))
    held = _cell_centers(sample, max(1, min(int(n**0.5), len(sample) // 8)), seed)
    visits = _cells_to_visit(rows, sample[:PROBES], [r.vec_id for r in drawn[:PROBES]], held, k, least_recall)
    cells = spark.sparkContext.broadcast(held)

    def homes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            home = np.argmax(_unit(batch.column(1)) @ cells.value.T, axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(home)], ["cell"])

    sizes = {r.cell: r.n for r in rows.mapInArrow(homes, "cell long").groupBy("cell").agg(F.count("*").alias("n")).collect()}
    parts = spark.sparkContext.broadcast(np.array([-(-sizes.get(c, 0) // CELL_ROWS) for c in range(len(held))]))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            near = np.argsort(-(_unit(batch.column(1)) @ cells.value.T), axis=1, kind="stable")[:, :visits]
            ids = batch.column(0).to_numpy()
            own, split = near[:, 0], parts.value
            row, cell, part, home = [np.arange(len(ids))], [own], [ids % np.maximum(1, split[own])], [np.ones(len(ids), bool)]
            for j in range(near.shape[1]):
                times = split[near[:, j]]
                row.append(np.repeat(np.arange(len(ids)), times))
                cell.append(np.repeat(near[:, j], times))
                part.append(np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times))
                home.append(np.zeros(times.sum(), bool))
            at = pa.array(np.concatenate(row))
            columns = [pa.array(np.concatenate(x)) for x in (cell, part, home)]
            yield pa.RecordBatch.from_arrays([*columns, batch.column(0).take(at), batch.column(1).take(at)], ["cell", "part", "home", "vec_id", "embedding"])

    def search(group: pa.Table) -> pa.Table:
        ids, home, unit = group.column("vec_id").to_numpy(), group.column("home").to_numpy(), _unit(group.column("embedding").combine_chunks())
        mine, found = ids[home], []
        visitors, unit, local = ids[~home], unit[~home], unit[home]
        for at in range(0, len(visitors), 1024):
            score = unit[at : at + 1024] @ local.T
            score[visitors[at : at + 1024][:, None] == mine[None, :]] = -np.inf
            a, b = _nearest(score, k)
            good = score[a, b] > -np.inf
            found.append((visitors[at + a[good]], mine[b[good]], 1 - score[a, b][good]))
        a, b, d = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        return pa.table({"a": a, "b": b, "distance": d})

    kind = dict(rows.dtypes)["embedding"]
    dealt = rows.mapInArrow(deal, f"cell long, part long, home boolean, vec_id long, embedding {kind}")
    pairs = dealt.groupBy("cell", "part").applyInArrow(search, "a long, b long, distance double")
    return pairs.withColumn("_r", F.row_number().over(Window.partitionBy("a").orderBy("distance", "b"))).where(F.col("_r") <= k).drop("_r")


def cluster_density(vectors: DataFrame, min_topic_size: int = 30, min_samples: int = 5, k: int = 15, levels: int = 8) -> DataFrame:
    """(vec_id, topic_id) by density, with a minimum size and an outlier class.

    Core distances and mutual reachability over a neighbour graph; the graph is cut at a ladder of distances
    and connected. Components of one cut lie within those of the next, so clusters of the minimum size form a
    tree, and those of the most excess of mass in it are taken (``_excess_of_mass``). It differs from a tree
    over every single distance in that clusters begin and end at the ladder's steps.
    """
    pairs = cut(near_pairs(vectors, k))
    nth = F.row_number().over(Window.partitionBy("a").orderBy("distance", "b"))
    core = pairs.withColumn("_r", nth).where(F.col("_r") == min_samples).select(F.col("a").alias("node"), F.col("distance").alias("core"))
    reach = pairs.join(core.withColumnsRenamed({"node": "a", "core": "core_a"}), "a").join(core.withColumnsRenamed({"node": "b", "core": "core_b"}), "b")
    reach = cut(reach.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.greatest("distance", "core_a", "core_b").alias("w")))
    steps = reach.agg(F.percentile_approx("w", [x / levels for x in range(1, levels + 1)], 1000)).first()[0] or []
    steps = sorted({max(x, 1e-9) for x in steps})
    cuts = [cut(components(reach.where(F.col("w") <= limit).select("src", "dst"))) for limit in steps]
    taken = _excess_of_mass(cuts, steps, min_topic_size)
    if taken is None:
        return vectors.select("vec_id", F.lit(OUTLIER).alias("topic_id"))
    order = taken.select("cluster").distinct().withColumn("topic_id", (F.row_number().over(Window.orderBy("cluster")) - 1).cast("int"))
    named = taken.join(F.broadcast(order), "cluster").select(F.col("node").alias("vec_id"), "topic_id")
    return vectors.select("vec_id").join(named, "vec_id", "left").fillna(OUTLIER, ["topic_id"])


def _excess_of_mass(cuts: list[DataFrame], steps: list[float], least: int) -> DataFrame | None:
    """(node, cluster) of the clusters that outweigh what they split into; None without any.

    ``cuts`` are (node, label) components from the finest cut to the coarsest. A cluster weighs its size times
    the range of 1 / distance that it lives through, above the coarsest cut; with one large part below it, it is
    the same cluster going on. A single cluster around all others is never taken if it splits.
    """
    states: list[DataFrame] = []
    for k, labels in enumerate(cuts):
        sizes = labels.groupBy("label").agg(F.count("*").alias("size")).where(F.col("size") >= least)
        lived = 1 / steps[k] - 1 / steps[min(k + 1, len(steps) - 1)]
        mass = F.col("size") * lived
        if not states:
            state = sizes.select("label", mass.alias("own"), mass.alias("best"), F.lit(True).alias("take"), F.lit(False).alias("splits"))
        else:
            up = states[-1].withColumnRenamed("label", "node").join(labels, "node")
            parts = up.groupBy("label").agg(F.count("*").alias("n"), F.sum("best").alias("below"), F.max("own").alias("one"), F.max("splits").alias("splits"))
            held = sizes.join(parts, "label", "left").withColumn("own", mass + F.when(F.col("n") == 1, F.col("one")).otherwise(0.0))
            below = F.coalesce("below", F.lit(0.0))
            splits = F.coalesce((F.col("n") > 1) | F.col("splits"), F.lit(False)).alias("splits")
            state = held.select("label", "own", F.greatest("own", below).alias("best"), (F.col("own") >= below).alias("take"), splits)
        states.append(cut(state))
    if not states or states[-1].isEmpty():
        return None
    alone = states[-1].count() == 1
    reached, taken = states[-1].select("label"), None
    for k in range(len(cuts) - 1, -1, -1):
        here = states[k].join(reached, "label", "left_semi")
        if alone:
            here = here.withColumn("take", F.col("take") & ~F.col("splits"))
        now = cuts[k].join(F.broadcast(here.where("take").select("label")), "label", "left_semi")
        now = now.select("node", F.concat_ws("|", F.lit(f"{k:03d}"), F.col("label").cast("string")).alias("cluster"))
        taken = now if taken is None else taken.unionByName(now)
        if not k:
            break
        rest = here.where("not take").select("label")
        inside = cuts[k].join(F.broadcast(rest), "label", "left_semi").select("node")
        reached = cut(states[k - 1].select("label").join(inside, F.col("label") == F.col("node"), "left_semi"))
        alone = alone and reached.count() == 1
    return cut(taken)


def random_topics(vectors: DataFrame, k: int, seed: int = 1) -> DataFrame:
    return vectors.select("vec_id", F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(k)).cast("int").alias("topic_id"))


def centers(labelled: DataFrame) -> DataFrame:
    """(topic_id, center): unit mean vector of each label."""
    cells = labelled.select(F.col("label").alias("topic_id"), F.posexplode("embedding").alias("i", "x"))
    means = cells.groupBy("topic_id", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    rows = means.groupBy("topic_id").agg(F.sort_array(F.collect_list(F.struct("i", "m"))).alias("c")).select("topic_id", F.col("c.m").alias("c"))
    return rows.select("topic_id", F.transform("c", lambda x: x / F.sqrt(dot(F.col("c"), F.col("c")))).alias("center"))


def soft_membership(vectors: DataFrame, held: DataFrame, temperature: float = 0.05) -> DataFrame:
    """(vec_id, topic_id, p): softmax of cosine similarity over the centers, one row for each pair.

    The centers are as many as there are topics, so they are broadcast.
    """
    scored = (
        vectors.select("vec_id", "embedding")
        .crossJoin(F.broadcast(held))
        .select("vec_id", "topic_id", F.exp(dot(F.col("embedding"), F.col("center")) / temperature).alias("e"))
    )
    return scored.select("vec_id", "topic_id", (F.col("e") / F.sum("e").over(Window.partitionBy("vec_id"))).alias("p"))


def hard_assign(members: DataFrame, key: str = "vec_id") -> DataFrame:
    """The most probable topic, the smaller id at a tie."""
    return members.groupBy(key).agg(F.max(F.struct("p", (-F.col("topic_id")).alias("t"))).alias("m")).select(key, (-F.col("m.t")).cast("int").alias("topic_id"))


def rescue_outliers(members: DataFrame, cut_p: float, p_min: float = 0.01, key: str = "vec_id") -> DataFrame:
    """(key, topic_id, p, rescued): the one topic of a clear row; every topic of an outlier at ``p_min`` or more."""
    best = F.max("p").over(Window.partitionBy(key))
    top = F.row_number().over(Window.partitionBy(key).orderBy(F.desc("p"), "topic_id"))
    ranked = members.select(key, "topic_id", "p", best.alias("_best"), top.alias("_top"))
    return (
        ranked.where(((F.col("_best") >= cut_p) & (F.col("_top") == 1)) | ((F.col("_best") < cut_p) & (F.col("p") >= p_min)))
        .select(key, "topic_id", "p", (F.col("_best") < cut_p).alias("rescued"))
    )


def class_tfidf(texts: DataFrame, low: int = 1, high: int = 3) -> DataFrame:
    """(topic_id, term, weight) of (topic_id, text) rows: frequency in the topic x log(1 + A / frequency overall).

    A is the mean number of terms of a topic.
    """
    grams = ngrams(F.split(clean_text(F.col("text")), " "), low, high)
    counts = texts.select("topic_id", F.explode(grams).alias("term")).where("term <> ''").groupBy("topic_id", "term").agg(F.count("*").alias("tf"))
    overall = counts.groupBy("term").agg(F.sum("tf").alias("all"))
    mean = counts.agg((F.sum("tf") / F.count_distinct("topic_id")).alias("a"))
    return (
        counts.join(overall, "term")
        .crossJoin(F.broadcast(mean))
        .select("topic_id", "term", (F.col("tf") * F.ln(1 + F.col("a") / F.col("all"))).alias("weight"))
    )


def top_terms(weights: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("topic_id").orderBy(F.desc(F.round("weight", 8)), "term")
    return weights.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def name_topics(weights: DataFrame, top_n_words: int = 15) -> DataFrame:
    """(topic_id, label): the topic's top terms joined by underscores."""
    rows = top_terms(weights, top_n_words).groupBy("topic_id").agg(F.sort_array(F.collect_list(F.struct("rank", "term"))).alias("t"))
    return rows.select("topic_id", F.array_join(F.col("t.term"), "_").alias("label"))


def topic_summary(assigned: DataFrame, key: str) -> DataFrame:
    """(topic_id, n_posts, share)."""
    total = assigned.agg(F.count_distinct(key).alias("total"))
    return (
        assigned.groupBy("topic_id")
        .agg(F.count_distinct(key).alias("n_posts"))
        .crossJoin(F.broadcast(total))
        .select("topic_id", "n_posts", (F.col("n_posts") / F.col("total")).alias("share"))
    )


def group_summary(members: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, n_topics, n_posts); a post counts once in a group, topics outside the map are dropped."""
    return (
        members.join(F.broadcast(groups), "topic_id")
        .groupBy("group_id")
        .agg(F.count_distinct("topic_id").alias("n_topics"), F.count_distinct("post_id").alias("n_posts"))
    )


def flag_noise_topics(texts: DataFrame, max_repeat: float = 0.5) -> DataFrame:
    """(topic_id, n, distinct_texts, noise): topics that mostly repeat the same texts."""
    return (
        texts.groupBy("topic_id")
        .agg(F.count("*").alias("n"), F.count_distinct(F.xxhash64("text")).alias("distinct_texts"))
        .withColumn("noise", F.col("distinct_texts") < (1 - max_repeat) * F.col("n"))
    )


def weekly_share(members: DataFrame, posts: DataFrame, denominator: str = "topic") -> DataFrame:
    """(topic_id, week, n, share) of all posts of the topic, or of all memberships of the week."""
    week = F.to_date(F.date_trunc("week", F.col("day"))).alias("week")
    counted = members.join(posts.select("post_id", "day"), "post_id").groupBy("topic_id", week).agg(F.count("*").alias("n"))
    whole = F.sum("n").over(Window.partitionBy("topic_id" if denominator == "topic" else "week"))
    return counted.select("topic_id", "week", "n", (F.col("n") / whole).alias("share"))


def pick_topics(groups: DataFrame, per_group: int = 2, seed: int | None = None) -> DataFrame:
    """(group_id, topic_id): some topics of each group, by a seeded hash or by a fixed modular order."""
    key = F.xxhash64(F.lit(seed), "topic_id") if seed is not None else (F.col("topic_id") * 7) % 23
    return (
        groups.withColumn("_r", F.row_number().over(Window.partitionBy("group_id").orderBy(key, "topic_id")))
        .where(F.col("_r") <= per_group)
        .select("group_id", "topic_id")
    )
