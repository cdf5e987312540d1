"""Quality rules: hashed n-gram log-likelihood ratio of a trusted target against the raw corpus.

Two multinomials over ``BUCKETS`` hashed byte 4-grams are counted: one over every document, one over the
trusted ones. A document's score is the mean over its 4-grams of log p_target - log p_raw, so length does
not matter; a document is kept when it passes the plain base rules and scores at least ``THRESHOLD``.
The rule is deterministic: equal texts get equal verdicts on equal corpora.

The trusted target is a bounded sample of labelled rows: the ``TRUSTED_ROWS`` labelled good with the
smallest hash of their id. Everything else covers all documents, whole texts. Only the two count vectors
(fixed size) reach the driver and are broadcast.

Defined cases
    Null or wordless text has no words, fails the base rules and is not kept. Without any trusted row the
    ratio is zero throughout, and the base rules alone decide. Repeated rows are counted and judged each.
    An empty table gives an empty result. Other columns, whatever their names, are carried untouched.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from discourselab.session import prepare

BUCKETS = 1 << 16
GRAM = 4
SMOOTH = 1.0
TRUSTED_ROWS = 20_000
THRESHOLD = -0.5

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
_SYMBOLS = b"#*$%&|<>"
_BLANK = " \t\n\v\f\r"


def trusted_ids(labels: DataFrame, rows: int = TRUSTED_ROWS) -> np.ndarray:
    """Sorted doc_ids of a bounded, repeatable sample of rows labelled good."""
    good = labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"))
    return np.unique(np.array([r.doc_id for r in good.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows).collect()], np.int64))


def _encode(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def grams(words: list[bytes]) -> np.ndarray:
    """Buckets of the byte 4-grams of a word sequence joined by single spaces."""
    whole = np.frombuffer(b" ".join(words), np.uint8).astype(np.uint32)
    if len(whole) < GRAM:
        return np.empty(0, np.int64)
    key = whole[:-3] | whole[1:-2] << np.uint32(8) | whole[2:-1] << np.uint32(16) | whole[3:] << np.uint32(24)
    return (key * np.uint32(2654435761) >> np.uint32(16)).astype(np.int64)


def base_rules(text: str | None, words: list[bytes]) -> tuple[int, int, int, int, int]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words) of one text."""
    text = text or ""
    blanks = sum(map(text.count, _BLANK))
    data = b"".join(words)
    symbols = len(data) - len(data.translate(None, _SYMBOLS))
    copies = 0
    if "\n" in text:
        times = Counter(text.split("\n"))
        copies = sum(n - 1 for line, n in times.items() if n > 1 and line.strip(_BLANK))
    n, repeated = len(words), 0
    if n > 3:
        windows = list(zip(words, words[1:], words[2:], strict=False))
        if len(set(windows)) < len(windows):
            times = Counter(windows)
            reach = -1
            for at, window in enumerate(windows):
                if times[window] > 1:
                    repeated += at + 2 - max(reach, at - 1)
                    reach = at + 2
    return n, len(text) - blanks, symbols, copies, repeated


def base_failed(n_words: int, n_repeat_words: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat_words > MAX_REPEAT_PERCENT * n_words


def _count_batches(trusted):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, target, known = np.zeros(BUCKETS, np.int64), np.zeros(BUCKETS, np.int64), trusted.value
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            good = np.isin(ids, known) if len(known) else np.zeros(len(ids), bool)
            for text, is_good in zip(batch.column(1), good, strict=True):
                counts = np.bincount(grams(_encode(text.as_py()).split()), minlength=BUCKETS)
                raw += counts
                if is_good:
                    target += counts
        seen = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(raw[seen]), pa.array(target[seen])], ["bucket", "raw", "target"])

    return run


def log_ratios(docs: DataFrame, trusted: np.ndarray) -> np.ndarray:
    """log p_target - log p_raw of every bucket, with additive smoothing; zeros if nothing is trusted."""
    spark = prepare(docs.sparkSession)
    pairs = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), "text")
    counted = pairs.mapInArrow(_count_batches(spark.sparkContext.broadcast(trusted)), "bucket int, raw long, target long")
    raw, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for row in counted.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect():
        raw[row.bucket], target[row.bucket] = row.raw, row.target
    if not target.sum():
        return np.zeros(BUCKETS)
    share = lambda counts: np.log((counts + SMOOTH) / (counts.sum() + SMOOTH * BUCKETS))
    return share(target) - share(raw)


def _judge(text: str | None, ratios: np.ndarray) -> tuple:
    words = _encode(text).split()
    rules = base_rules(text, words)
    found = grams(words)
    score = float(ratios[found].mean()) if len(found) else 0.0
    failed = base_failed(rules[0], rules[4])
    return (*rules, failed, score, not failed and score >= THRESHOLD)


_VERDICT = {
    "n_words": pa.int64(),
    "word_chars": pa.int64(),
    "n_symbols": pa.int64(),
    "n_dup_lines": pa.int64(),
    "n_repeat_words": pa.int64(),
    "base_failed": pa.bool_(),
    "score": pa.float64(),
    "kept": pa.bool_(),
}


def judge(docs: DataFrame, trusted: np.ndarray) -> DataFrame:
    """doc_id, base counts, base_failed, score and kept of every row of a (doc_id, text) table."""
    ratios = docs.sparkSession.sparkContext.broadcast(log_ratios(docs, trusted))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [_judge(text.as_py(), ratios.value) for text in batch.column(1)]
            columns = zip(*rows, strict=True) if rows else [[]] * len(_VERDICT)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), *(pa.array(list(x), kind) for x, kind in zip(columns, _VERDICT.values(), strict=True))],
                ["doc_id", *_VERDICT],
            )

    return (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        .mapInArrow(
            run,
            "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, score double, kept boolean",
        )
    )


def keep_good(docs: DataFrame, trusted: np.ndarray) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns."""
    ratios = docs.sparkSession.sparkContext.broadcast(log_ratios(docs, trusted))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([_judge(text.as_py(), ratios.value)[-1] for text in batch.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
