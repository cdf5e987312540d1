"""Benchmark contamination by a prefix-filtered set join of word shingles.

An item's window is 13 consecutive words (a shorter item is one window). A document contains a window
only if it contains all of the window's shingles, so the overlap that is needed is the whole set and the
necessary prefix, in an order that starts at the rarest shingle, is that one shingle. Rarity is the number
of documents that hold the shingle, counted over the whole corpus. Each document joins its shingles with
the prefixes; a joined pair fixes where the window would start; the positional bound drops starts before
the first word and the length bound those that run past the last; the rest are compared word for word.

The items are a query set: they are taken in blocks of at most ``BLOCK_BYTES`` of text, one after another, so
what the driver holds and broadcasts has a fixed bound however large the item table is. A block is two
narrow passes over the documents: one counts rarity, one matches. Items that fit one block, as benchmarks
do, need no more. With more blocks, what each finds is written by the hash of the text (128 bits) before the
next is built, and comes together by one join at the end.

Defined cases
    Null text has no words and is clean. Null or wordless items have no window. Rows that repeat an
    item_id count as one item; a null item_id counts as an item named ``null``. Repeated documents are
    judged each. Empty tables give an empty result, or clean documents. Other columns are untouched.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from discourselab.llm.columns import unused
from discourselab.session import prepare, scratch

WINDOW = 13
SHINGLE = 5
BLOCK_BYTES = 8_000_000
#: A document is contaminated if at least one word in ``SHARE`` is hit.
SHARE = 20

_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
_BASE = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[bytes]:
    """Words of a text: runs of ASCII letters (folded), digits and whatever is not ASCII."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()


def _shingle_keys(ids: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of the runs of ``size`` known words in a sequence of word ids, and where they start."""
    n = len(ids) - size + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    known = np.concatenate(([0], np.cumsum(ids >= 0)))
    starts = np.flatnonzero(known[size:] - known[:-size] == size)
    key = np.zeros(len(starts), np.uint64)
    for k in range(size):
        key = (key ^ ids[starts + k].astype(np.uint64) + np.uint64(1)) * _BASE
        key ^= key >> np.uint64(29)
    return key, starts


class Block:
    """Windows of a bounded set of items, and the prefix tokens that lead to them."""

    def __init__(self, items: list[tuple[str, str | None]]) -> None:
        self.vocabulary: dict[bytes, int] = {}
        windows: dict[tuple[int, ...], set[str]] = {}
        for item, text in items:
            ids = [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words_of(text)]
            for at in range(max(1, len(ids) - WINDOW + 1) if ids else 0):
                windows.setdefault(tuple(ids[at : at + WINDOW]), set()).add(item)
        self.windows = [np.array(w, np.int64) for w in windows]
        self.items = [sorted(x) for x in windows.values()]
        self.sizes = sorted({min(SHINGLE, len(w)) for w in self.windows})
        self.own = [_shingle_keys(w, min(SHINGLE, len(w))) for w in self.windows]
        self.keys = np.unique(np.concatenate([k for k, _ in self.own])) if self.own else np.empty(0, np.uint64)

    def ids(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.vocabulary.get, words, repeat(-1)), np.int64, len(words))

    def seen(self, words: list[bytes]) -> np.ndarray:
        """Numbers of this block's shingles that a document holds, each once."""
        ids, found = self.ids(words), []
        for size in self.sizes:
            key, _ = _shingle_keys(ids, size)
            at = np.searchsorted(self.keys, key)
            at[at == len(self.keys)] = 0
            found.append(at[self.keys[at] == key] if len(self.keys) else at[:0])
        return np.unique(np.concatenate(found)) if found else np.empty(0, np.int64)

    def order(self, frequency: np.ndarray) -> None:
        """Choose each window's prefix: its rarest shingle, the smaller key at a tie."""
        chosen: dict[int, list[tuple[int, int]]] = {}
        for window, (key, starts) in enumerate(self.own):
            rank = np.lexsort((key, frequency[np.searchsorted(self.keys, key)]))[0]
            chosen.setdefault(int(key[rank]), []).append((window, int(starts[rank])))
        self.prefix = np.array(sorted(chosen), np.uint64)
        self.leads = [chosen[int(k)] for k in self.prefix]
        del self.own, self.keys

    def match(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """(start, end) of every occurrence of a window in a document, and the items these belong to."""
        spans, items = set(), set()
        if not len(self.prefix):
            return [], items
        ids = self.ids(words)
        for size in self.sizes:
            key, starts = _shingle_keys(ids, size)
            at = np.searchsorted(self.prefix, key)
            at[at == len(self.prefix)] = 0
            hit = self.prefix[at] == key
            for lead, position in zip(at[hit].tolist(), starts[hit].tolist(), strict=True):
                for window, offset in self.leads[lead]:
                    content, begin = self.windows[window], position - offset
                    end = begin + len(content)
                    if begin >= 0 and end <= len(ids) and np.array_equal(ids[begin:end], content):
                        spans.add((begin, end))
                        items.update(self.items[window])
        return sorted(spans), items


def blocks(items: DataFrame, block_bytes: int = BLOCK_BYTES) -> tuple[int, Iterator[Block]]:
    """How many blocks of about ``block_bytes`` of text at most, and the blocks; items are dealt by a hash of their id."""
    rows = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item"), F.col("text"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    count = max(1, math.ceil(size / block_bytes))
    build = lambda k: Block([(r.item, r.text) for r in rows.where(F.pmod(F.xxhash64("item"), F.lit(count)) == k).collect()])
    return count, map(build, range(count))


def _frequencies(docs: DataFrame, block: Block) -> np.ndarray:
    held = docs.sparkSession.sparkContext.broadcast(block)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(len(held.value.keys), np.int64)
        for batch in batches:
            for text in batch.column(0):
                counts[held.value.seen(words_of(text.as_py()))] += 1
        some = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(counts[some])], ["shingle", "n"])

    total = np.zeros(len(block.keys), np.int64)
    for row in docs.select("text").mapInArrow(run, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).collect():
        total[row.shingle] = row.n
    return total


_DIGEST = {"n_words": pa.int64(), "n_hit": pa.int64(), "n_items": pa.int64(), "items_sha256": pa.string(), "contaminated": pa.bool_()}
_DIGEST_TYPE = StructType().add("n_words", "long").add("n_hit", "long").add("n_items", "long").add("items_sha256", "string").add("contaminated", "boolean")
_FOUND_SQL = "a long, b long, spans array<bigint>, items array<string>"


def _digest(n: int, spans: list[tuple[int, int]], items: set[str]) -> tuple:
    hit = reach = 0
    for begin, end in sorted(spans):
        hit += max(0, end - max(begin, reach))
        reach = max(reach, end)
    return n, hit, len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), hit > 0 and SHARE * hit >= n


def _pairs(flat: list[int]) -> list[tuple[int, int]]:
    return list(zip(flat[::2], flat[1::2], strict=True))


def _found_in(texts: DataFrame, counted: Iterator[Block]) -> DataFrame:
    """(a, b, spans, items) of the texts, by the hash (a, b), in which some block's windows occur."""
    spark = texts.sparkSession
    folder = scratch(spark, "decontaminate")
    for block in counted:
        block.order(_frequencies(texts, block))
        held = spark.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = [held.value.match(words_of(text.as_py())) for text in batch.column("text")]
                some = pa.array([bool(spans) for spans, _ in found])
                spans = pa.array([[x for s in spans for x in s] for spans, _ in found if spans], pa.list_(pa.int64()))
                items = pa.array([sorted(items) for spans, items in found if spans], pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([batch.column("a").filter(some), batch.column("b").filter(some), spans, items], ["a", "b", "spans", "items"])

        texts.mapInArrow(run, _FOUND_SQL).dropDuplicates(["a", "b"]).write.mode("append").parquet(folder)
        held.destroy()
    flat = lambda c: F.flatten(F.collect_list(c)).alias(c)
    return spark.read.schema(_FOUND_SQL).parquet(folder).groupBy("a", "b").agg(flat("spans"), flat("items"))


def contamination(docs: DataFrame, items: DataFrame, carry: list[str], digest: str, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Columns ``carry`` of every document and a struct ``digest`` of its contamination."""
    spark = prepare(docs.sparkSession)
    count, todo = blocks(items, block_bytes)
    rows = docs.select(*dict.fromkeys([*carry, "text"]))
    held = None
    spans, found = unused(rows, "spans", "items")
    if count == 1:
        block = next(todo)
        block.order(_frequencies(rows, block))
        held = spark.sparkContext.broadcast(block)
    else:
        hashes = [F.xxhash64("text").alias("a"), F.xxhash64(F.lit("other"), "text").alias("b")]
        key = unused(rows, "a", "b", "c", "d")
        hits = _found_in(rows.select(*hashes, "text"), todo).toDF(key[2], key[3], spans, found)
        named = rows.select("*", *(x.alias(k) for x, k in zip(hashes, key, strict=False)))
        rows = named.join(hits, (F.col(key[0]) == F.col(key[2])) & (F.col(key[1]) == F.col(key[3])), "left").drop(*key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            before = repeat(None) if held else zip(batch.column(spans).to_pylist(), batch.column(found).to_pylist(), strict=True)
            for text, old in zip(batch.column("text"), before, strict=False):
                words = words_of(text.as_py())
                where, which = held.value.match(words) if held else (_pairs(old[0] or []), set(old[1] or []))
                out.append(dict(zip(_DIGEST, _digest(len(words), where, which), strict=True)))
            yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in carry), pa.array(out, pa.struct(list(_DIGEST.items())))], [*carry, digest])

    schema = StructType([*(f for f in docs.select(*carry).schema), StructField(digest, _DIGEST_TYPE)])
    return rows.mapInArrow(run, schema)


def scan(docs: DataFrame, items: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256 and contaminated of every document."""
    return contamination(docs, items, ["doc_id"], "digest", block_bytes).select(F.col("doc_id").cast("long").alias("doc_id"), "digest.*")


def keep_clean(docs: DataFrame, items: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The documents that are not contaminated, with all their columns."""
    (digest,) = unused(docs, "digest")
    return contamination(docs, items, docs.columns, digest, block_bytes).where(~F.col(f"{digest}.contaminated")).select(*docs.columns)
