"""Language identification by prediction by partial matching.

For each language a byte context tree of order ``ORDER`` is counted once and frozen. A byte is coded in the
longest context that the language knows; a byte never seen there costs the context's escape probability
(distinct symbols over symbols plus distinct symbols) and is coded one order lower, without the symbols that
the longer context has, down to a uniform code over the bytes that the language never has. So the code
lengths are those of a proper code: the probabilities of all bytes in a context sum to one. The exact code
length of a text under each language's tree decides: the shortest wins, the smaller name at a tie, and the
score is the posterior of the winner under equal priors.

The trees are kept as sorted arrays of the strings that occur, each with its counts by language, so their size
follows what was seen and not the alphabet. A text costs one look-up a byte; strings that no language has
are coded once for each different one. Texts are lower-cased and everything but letters counts as one space.

The model is fitted on a bounded sample of labelled rows: about ``SAMPLE_DOCS`` whole texts a language,
chosen by a hash of the id among rows that are not held out. Every document is scored whole, in one
narrow pass. What is broadcast depends on the sample alone.

Defined cases
    A null text, or one without a letter, is ``und`` with score 0; so is every text if nothing could be
    learned. Rows with a null doc_id are scored, not held out, and never learned from. Repeated rows are
    scored each. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from discourselab.session import prepare

ORDER = 3
SAMPLE_DOCS = 400
UNKNOWN = "und"

_FOLD = bytes(c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))
_LETTER = regex.compile(r"\p{L}")


def normal(text: str) -> np.ndarray:
    """Bytes of a lower-cased text, led by ``ORDER`` spaces, with one space for each run of non-letters."""
    words = text.lower().encode("utf-8", "surrogatepass").translate(_FOLD).split()
    return np.frombuffer(b" " * ORDER + b" ".join(words) + b" ", np.uint8)


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))


def _find(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Where the wanted values stand in sorted keys; -1 for those that do not."""
    at = np.searchsorted(keys, wanted)
    at[at == len(keys)] = 0
    return np.where(keys[at] == wanted, at, -1)


def _last(strings: np.ndarray, size: int) -> np.ndarray:
    """The last bytes of byte strings held as numbers."""
    return strings & ((1 << 8 * size) - 1)


class Trees:
    """Frozen context trees of all languages.

    By order: ``strings`` (context and byte, sorted) with their ``counts``, ``contexts`` (sorted), and the code of
    a context as bits: what a byte costs besides -log2 of its count, and what the escape costs. ``plain`` is the
    code of a context reached first, ``shorter`` that of its suffix after an escape from it.
    """

    def __init__(self, counts: dict[str, dict[int, int]]) -> None:
        """counts: for each language, how often each 4-byte string (first byte highest) occurs."""
        self.languages = sorted(counts)
        grams = [np.array(sorted(counts[x]), np.int64) for x in self.languages]
        every = np.unique(np.concatenate(grams)) if grams else np.empty(0, np.int64)
        table = np.zeros((len(every), len(self.languages)))
        for x, (name, own) in enumerate(zip(self.languages, grams, strict=True)):
            table[np.searchsorted(every, own), x] = [counts[name][g] for g in own.tolist()]
        self.strings, self.counts, self.contexts, self.plain, self.shorter = {}, {}, {}, {}, {}
        if not len(every):
            return
        total, kinds, home = {}, {}, {}
        for order in range(ORDER, -1, -1):
            self.strings[order], back = np.unique(_last(every, order + 1), return_inverse=True)
            self.counts[order] = self._summed(back, table, len(self.strings[order]))
            self.contexts[order], home[order] = np.unique(self.strings[order] >> 8, return_inverse=True)
            total[order] = self._summed(home[order], self.counts[order], len(self.contexts[order]))
            kinds[order] = self._summed(home[order], self.counts[order] > 0, len(self.contexts[order]))
            self.plain[order] = self._code(total[order], kinds[order])
        for order in range(1, ORDER + 1):
            suffix = _find(self.contexts[order - 1], _last(self.contexts[order], order - 1))
            below = self.counts[order - 1][_find(self.strings[order - 1], _last(self.strings[order], order))]
            known = self._summed(home[order], np.where(self.counts[order] > 0, below, 0), len(self.contexts[order]))
            self.shorter[order] = self._code(total[order - 1][suffix] - known, kinds[order - 1][suffix] - kinds[order])
        self.unseen = np.log2(np.maximum(1, 256 - kinds[0][0]))
        self.bits = self.lengths_of(self.strings[ORDER]).astype(np.float32)

    @staticmethod
    def _summed(group: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
        out = np.zeros((n, values.shape[1]))
        np.add.at(out, group, values)
        return out

    @staticmethod
    def _code(total: np.ndarray, kinds: np.ndarray) -> np.ndarray:
        """Bits besides -log2 of a count, and of the escape; no bits where nothing is left to escape from."""
        some = kinds > 0
        whole = np.log2(np.where(some, total + kinds, 1))
        return np.stack([whole, whole - np.log2(np.where(some, kinds, 1))])

    def lengths_of(self, strings: np.ndarray) -> np.ndarray:
        """Code length in bits of the last byte of 4-byte strings after the others, by language."""
        spent = np.zeros((len(strings), len(self.languages)))
        out, open_ = np.zeros_like(spent), np.ones(spent.shape, bool)
        for order in range(ORDER, -1, -1):
            here = _find(self.contexts[order], _last(strings >> 8, order))
            whole, escape = np.where((here >= 0)[:, None], self.plain[order][:, here], 0)
            if order < ORDER:
                above = _find(self.contexts[order + 1], _last(strings >> 8, order + 1))
                whole, escape = np.where((above >= 0)[:, None], self.shorter[order + 1][:, above], [whole, escape])
            at = _find(self.strings[order], _last(strings, order + 1))
            n = np.where((at >= 0)[:, None], self.counts[order][at], 0)
            coded = open_ & (n > 0)
            out[coded] = (spent + whole)[coded] - np.log2(n[coded])
            open_ &= ~coded
            spent += escape
        return np.where(open_, spent + self.unseen, out)

    def lengths(self, text: str) -> np.ndarray:
        """Code length of a text in bits, by language."""
        b = normal(text).astype(np.int64)
        strings = b[:-3] << 24 | b[1:-2] << 16 | b[2:-1] << 8 | b[3:]
        strings.sort()  # the order of a sum is no matter, and sorted look-ups stay in the cache
        at = _find(self.strings[ORDER], strings)
        bits = self.bits[at[at >= 0]].sum(axis=0, dtype=np.float64)
        if (at < 0).any():
            strange, times = np.unique(strings[at < 0], return_counts=True)
            bits += times @ self.lengths_of(strange)
        return bits

    def predict(self, text: str | None) -> tuple[str, float]:
        if not self.languages or not text or not _LETTER.search(text):
            return UNKNOWN, 0.0
        bits = self.lengths(text)
        best = int(np.argmin(bits))
        return self.languages[best], float(1 / np.exp2(np.maximum(bits[best] - bits, -1000)).sum())


def _gram_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        parts: dict[str, list[np.ndarray]] = {}
        for lang, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            b = normal(text.as_py()).astype(np.int64)
            parts.setdefault(lang, []).append(b[:-3] << 24 | b[1:-2] << 16 | b[2:-1] << 8 | b[3:])
        for lang, grams in parts.items():
            gram, n = np.unique(np.concatenate(grams), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(gram), pa.string()), pa.array(gram), pa.array(n)], ["lang", "gram", "n"])


def learn(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Trees:
    """Trees from a bounded, repeatable sample of the rows of (doc_id, text, lang) that are not held out."""
    prepare(docs.sparkSession)
    labelled = docs.where(~held_out() & F.col("doc_id").isNotNull() & F.col("lang").isNotNull())
    sizes = {r.lang: r.n for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return Trees({})
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, min(1.0, sample_docs / n)).otherwise(share)
    draw = F.pmod(F.xxhash64(F.lit("sample"), F.col("doc_id")), F.lit(1 << 30)) / float(1 << 30)
    sample = labelled.where((draw < share) & F.col("text").isNotNull()).select("lang", "text")
    counts: dict[str, dict[int, int]] = {}
    for r in sample.mapInArrow(_gram_batches, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).collect():
        counts.setdefault(r.lang, {})[r.gram] = r.n
    return Trees(counts)


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred and score of every row of a (doc_id, text, lang) table."""
    held = docs.sparkSession.sparkContext.broadcast(learn(docs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = held.value.predict
        for batch in batches:
            found = [predict(text.as_py()) for text in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())],
                ["doc_id", "held_out", "lang_pred", "score"],
            )

    return (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), "text")
        .mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
    )
