"""Near-duplicate documents by 64-bit fingerprints and vantage-point trees.

A fingerprint is the bitwise majority of the XXH64 values of a text's 3-word shingles. Two fingerprints
are linked at ``radius`` (3) or fewer differing bits; documents are grouped by reachability over links.

How exact pairs are found
    A fingerprint is cut into two 32-bit halves. Of two fingerprints at most 3 bits apart one half
    differs in at most 1 bit, so each half is searched on its own with radius 1. Over each half stands a
    vantage-point tree: a node holds a pivot and the median distance of a bounded sample to it; points
    within the median go to the inner shard, the others to the outer one. By the triangle inequality a
    partner at distance r or less of a point at distance d lies between d - r and d + r of the pivot, so
    a point is also sent, as a visitor, to the other side only where that interval crosses the median.
    The upper levels deal points to shards (one Spark group each), the lower levels are walked inside a
    shard with numpy, and the leaves compare whole fingerprints. No pair is lost and none is guessed.
    Where many points share a half, distances to it tell nothing: such shards are dealt again, and such
    leaves walked again, by trees over the two quarters of the other half (of at most 3 differing bits one
    quarter has at most 1), inside a leaf down to single bytes.

Scale
    Only distinct fingerprints are searched; copies fold into the smallest doc_id by a map-side combined
    aggregate. The tree's size follows the number of distinct fingerprints, its sample is bounded
    (``SAMPLE``). A shard gives a spanning forest of its links and not its pairs, so a group of n near
    copies costs n rows. Components come from alternating star contraction over written tables.

Defined cases
    Null or wordless text has fingerprint zero, linked like any other. Rows with a null doc_id take part
    in links, never name a component, and get the component of the others in their group (null if none).
    Rows are told apart by their text: rows of one doc_id with different texts are linked only by their
    fingerprints. Repeated rows keep one output row each. An empty table gives an empty result.
    ``keep_one_each`` keeps one row of every group: that of the smallest doc_id (rows without one come
    last), of the smallest text hash among those, and one of equal rows. Other columns are carried
    untouched, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from discourselab.llm.columns import unused
from discourselab.plans.iterate import components
from discourselab.session import cut, prepare

SEED = 42
SHINGLE = 3
RADIUS = 3
#: Distinct fingerprints that fit the trees' pivots and medians: a bound on what the driver sees.
SAMPLE = 8192
#: Distinct fingerprints that a shard is meant to hold.
SHARD_ROWS = 16384
#: Routed points from which on a shard is dealt again.
HOT_ROWS = 32 * SHARD_ROWS
#: Points that a leaf inside a shard may hold before it is split again.
LEAF = 96


def fingerprint(text: str | None) -> int:
    """Fingerprint of one text as an unsigned 64-bit number."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    whole = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    n = max(1, len(words) - SHINGLE + 1)
    digest = xxhash.xxh64_intdigest
    tails = ends[SHINGLE - 1 :] if len(words) >= SHINGLE else ends[-1:]
    hashes = np.fromiter((digest(whole[a:b], SEED) for a, b in zip(starts[:n].tolist(), tails.tolist(), strict=True)), np.uint64, n)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 16):
        part = hashes[at : at + (1 << 16)]
        ones += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int((np.uint64(1) << np.flatnonzero(2 * ones > n).astype(np.uint64)).sum(dtype=np.uint64))


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        values = np.fromiter((fingerprint(x.as_py()) for x in batch.column(1)), np.uint64, batch.num_rows)
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(values.view(np.int64))], ["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) of every row; fp holds the 64 bits as a signed long."""
    prepare(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_fingerprint_batches, "doc_id long, fp long")


class Tree:
    """Upper levels of a vantage-point tree over fields of ``width`` bits, laid out as a heap."""

    def __init__(self, sample: np.ndarray, depth: int, seed: int, width: int = 32) -> None:
        self.depth = depth
        count = (1 << depth) - 1
        self.pivots = np.random.default_rng(seed).integers(0, 1 << width, count, dtype=np.uint32)
        self.medians = np.full(count, width // 2, np.int64)
        held = {0: sample}
        for node in range(count):
            mine = held.pop(node)
            distance = np.bitwise_count(mine ^ self.pivots[node]).astype(np.int64)
            if len(mine) >= 8:
                self.medians[node] = int(np.median(distance))
            inner = distance <= self.medians[node]
            held[2 * node + 1], held[2 * node + 2] = mine[inner], mine[~inner]

    def route(self, points: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(index, shard, is home) of every shard a point has to be seen in."""
        index, node, home = np.arange(len(points)), np.zeros(len(points), np.int64), np.ones(len(points), bool)
        for _ in range(self.depth):
            distance = np.bitwise_count(points[index] ^ self.pivots[node]).astype(np.int64)
            bound = self.medians[node]
            inside, go_in, go_out = distance <= bound, distance - radius <= bound, distance + radius > bound
            index, home, node = (
                np.concatenate([index[go_in], index[go_out]]),
                np.concatenate([(home & inside)[go_in], (home & ~inside)[go_out]]),
                np.concatenate([2 * node[go_in] + 1, 2 * node[go_out] + 2]),
            )
        return index, node - ((1 << self.depth) - 1), home


class Forest:
    """Union-find whose finds are vectorised; roots are the smallest members."""

    def __init__(self, n: int) -> None:
        self.up = np.arange(n)

    def roots(self) -> np.ndarray:
        while True:
            above = self.up[self.up]
            if np.array_equal(above, self.up):
                return self.up
            self.up = above

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            roots = self.roots()
            x, y = roots[a], roots[b]
            a, b = a[x != y], b[x != y]
            low, high = np.minimum(x, y)[x != y], np.maximum(x, y)[x != y]
            np.minimum.at(self.up, high, low)


def _field(fp: np.ndarray, low: int, width: int) -> np.ndarray:
    """Some bits of fingerprints."""
    return (fp >> np.uint64(low) & np.uint64((1 << width) - 1)).astype(np.uint32)


def _others(low: int, width: int) -> list[tuple[int, int]]:
    """The two parts (lowest bit, width) of the field beside this one."""
    beside, half = low ^ width, width // 2
    return [(beside, half), (beside + half, half)]


def shard_links(fp: np.ndarray, home: np.ndarray, half: int, radius: int = RADIUS, leaf: int = LEAF) -> np.ndarray:
    """Root of each point in the forest of links between a home point and any point of the shard.

    ``half`` (0 or 1) is the 32-bit half that the shard's tree is built over; points at most radius // 2
    apart in it are compared. The walk keeps its own stack, so its depth is no matter.
    """
    forest, reach = Forest(len(fp)), radius // 2
    rng = np.random.default_rng(7)
    todo = [(np.flatnonzero(home), np.flatnonzero(~home), 32 * half, 32, 0)]
    while todo:
        mine, seen, low, width, failed = todo.pop()
        if not len(mine):
            continue
        if len(mine) > leaf and failed < 3:
            near, far = _field(fp[mine], low, width), _field(fp[seen], low, width)
            pivot = near[rng.integers(len(mine))] ^ np.uint32(rng.integers(1 << width) if failed == 0 else 0)
            d, e = (np.bitwise_count(x ^ pivot).astype(np.int64) for x in (near, far))
            bound = int(np.median(d))
            bound -= bound == d.max()
            inner = d <= bound
            if 8 * min(inner.sum(), (~inner).sum()) < len(mine):
                todo.append((mine, seen, low, width, failed + 1))
                continue
            for side, within, beyond in ((inner, d - reach <= bound, e - reach <= bound), (~inner, d + reach > bound, e + reach > bound)):
                todo.append((mine[side], np.concatenate([mine[~side & within], seen[beyond]]), low, width, 0))
            continue
        if len(mine) > leaf and width > 8:
            todo += [(mine, seen, *field, 0) for field in _others(low, width)]
            continue
        others = np.concatenate([mine, seen])
        step = max(1, 2_000_000 // len(others))
        for at in range(0, len(mine), step):
            rows = mine[at : at + step]
            x, y = np.nonzero(np.bitwise_count(fp[rows][:, None] ^ fp[others][None, :]) <= radius)
            x, y = rows[x], others[y]
            forest.join(x[x != y], y[x != y])
    return forest.roots()


class Routes:
    """Where a point has to be seen: by the tree over each half, and in hot shards by trees over quarters."""

    def __init__(self, sample: np.ndarray, depth: int) -> None:
        self.trees = [Tree(_field(sample, 32 * k, 32), depth, seed=11 + k) for k in (0, 1)]
        self.hot = [np.empty(0, np.int64)] * 2
        self.finer: list[list[Tree]] = []

    def deal_again(self, hot: list[np.ndarray], sample: np.ndarray, depth: int) -> None:
        """Split the shards listed by half further, by trees over the quarters of the other half."""
        self.hot = hot
        self.finer = [[Tree(_field(sample, *field), depth, seed=31 + q, width=16) for q, field in enumerate(_others(32 * k, 32))] for k in (0, 1)]

    def __call__(self, bits: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(half, index, shard, part, is home); part is 0 in shards that are not split."""
        for k, tree in enumerate(self.trees):
            index, shard, home = tree.route(_field(bits, 32 * k, 32), RADIUS // 2)
            split = np.isin(shard, self.hot[k])
            yield k, index[~split], shard[~split], np.zeros((~split).sum(), np.int64), home[~split]
            if split.any():
                index, shard, home = index[split], shard[split], home[split]
                for q, field in enumerate(_others(32 * k, 32)):
                    at, leaf, own = self.finer[k][q].route(_field(bits[index], *field), RADIUS // 2)
                    yield k, index[at], shard[at], 1 + 2 * leaf + q, home[at] & own


def _route_batches(routes):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = batch.column("fp").to_numpy(zero_copy_only=False)
            for k, index, shard, part, home in routes.value(fp.view(np.uint64)):
                for at in range(0, len(index), 1 << 18):
                    cell = slice(at, at + (1 << 18))
                    columns = [np.full(len(index[cell]), k, np.int32), shard[cell], part[cell], fp[index[cell]], home[cell]]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], ["half", "shard", "part", "fp", "home"])

    return run


def _link_shard(group: pa.Table) -> pa.Table:
    fp = group.column("fp").to_numpy()
    order = np.argsort(fp, kind="stable")
    fp, home = fp[order], group.column("home").to_numpy()[order]
    roots = shard_links(fp.view(np.uint64), home, group.column("half")[0].as_py())
    linked = roots != np.arange(len(fp))
    return pa.table({"src": pa.array(fp[linked]), "dst": pa.array(fp[roots[linked]])})


def _sampled(points: DataFrame) -> np.ndarray:
    return np.array([r.fp for r in points.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(SAMPLE).collect()], np.int64).view(np.uint64)


def fingerprint_groups(points: DataFrame, shard_rows: int = SHARD_ROWS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """(fp, root) of every distinct fingerprint of a table with a column fp; the root names its group."""
    sc = points.sparkSession.sparkContext
    classes = cut(points.select("fp").distinct())
    n = classes.count()
    routes = Routes(_sampled(classes), max(0, int(np.ceil(np.log2(max(1, n) / shard_rows)))) + 2)
    dealt = lambda: classes.mapInArrow(_route_batches(sc.broadcast(routes)), "half int, shard long, part long, fp long, home boolean")
    sizes = dealt().groupBy("half", "shard").agg(F.count("*").alias("n")).where(F.col("n") > hot_rows).collect()
    if sizes:  # at most as many as routed points over hot_rows
        deeper = int(np.ceil(np.log2(max(r.n for r in sizes) / shard_rows)))
        hot = [np.array(sorted(r.shard for r in sizes if r.half == k), np.int64) for k in (0, 1)]
        held = dealt().join(F.broadcast(points.sparkSession.createDataFrame([(r.half, r.shard) for r in sizes], "half int, shard long")), ["half", "shard"])
        routes.deal_again(hot, _sampled(held.select("fp").distinct()), deeper)
    links = cut(dealt().groupBy("half", "shard", "part").applyInArrow(_link_shard, "src long, dst long"))
    roots = components(links)
    return classes.join(roots, classes.fp == roots.node, "left").select("fp", F.coalesce("label", "fp").alias("root"))


def link_components(points: DataFrame, **sizes: int) -> DataFrame:
    """(fp, component_id) of every distinct fingerprint of a (doc_id, fp) table."""
    least = points.groupBy("fp").agg(F.min("doc_id").alias("rep"))
    held = cut(least.join(fingerprint_groups(points, **sizes), "fp"))
    return held.join(held.groupBy("root").agg(F.min("rep").alias("component_id")), "root").select("fp", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row of a (doc_id, text) table."""
    points = cut(fingerprints(docs))
    return points.join(link_components(points), "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one_each(docs: DataFrame) -> DataFrame:
    """One row of ``docs`` for every group of near copies."""
    key, doc, text = unused(docs, "key", "doc", "hash")
    rows = docs.withColumn(text, F.xxhash64(F.coalesce("text", F.lit(""))))
    points = cut(rows.select(F.col("doc_id").cast("long").alias("doc_id"), "text", text).mapInArrow(_row_points, "doc_id long, fp long, hash long"))
    first = F.min(F.struct(F.isnull("doc_id").alias("last"), "doc_id", "hash")).alias("x")
    stays = points.join(fingerprint_groups(points), "fp").groupBy("root").agg(first).select(F.col("x.doc_id").alias(doc), F.col("x.hash").alias(key))
    kept = rows.join(stays, rows["doc_id"].cast("long").eqNullSafe(stays[doc]) & (rows[text] == stays[key]), "left_semi")
    repeated = points.groupBy("doc_id", "hash").agg(F.count("*").alias("n")).where("n > 1")
    return (kept if repeated.isEmpty() else kept.dropDuplicates(["doc_id", text])).select(*docs.columns)


def _row_points(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        values = np.fromiter((fingerprint(x.as_py()) for x in batch.column(1)), np.uint64, batch.num_rows)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values.view(np.int64)), batch.column(2)], ["doc_id", "fp", "hash"])
