"""Token counts by heap-and-linked-list byte-pair merging.

A word's byte symbols form a doubly linked list; adjacent pairs that a rule merges wait in a heap by rank
and position. The lowest is popped, stale entries are passed over, the pair is merged and its new
neighbours are pushed. The count is the number of initial symbols minus the number of merges; no token is
ever named. A word of n symbols costs O(n log n), however long. Words repeat, so each worker keeps the
counts of the words it has seen, up to ``CACHE`` of them.

One narrow pass; nothing is shuffled. Special strings inside texts count as one token each, as the
tokenizer file's own library takes them.

Defined cases
    Null text counts as empty: no bytes, no tokens. Repeated rows are counted each. An empty table gives
    an empty result. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from discourselab.session import prepare

LIMIT = 2048
CACHE = 1_000_000
#: White space and word pattern of the word-level tokenizer file (fixed values of that file).
_SPACE = r"\t-\r\x20\x85\xa0  -     　"
_WORDS = rf"'s|'t|'re|'ve|'m|'ll|'d|\p{{L}}+|\p{{N}}|[^{_SPACE}\p{{L}}\p{{N}}]+"

_COUNTERS: dict[str, TokenCounter] = {}


class TokenCounter(dict):
    """Counts tokens by a word-level byte-pair tokenizer file; as a mapping, tokens by word."""

    def __init__(self, content: bytes) -> None:
        super().__init__()
        file = json.loads(content)
        model = file["model"]
        self.ending = model["end_of_word_suffix"] or ""
        self.known = model["vocab"]
        self.rank = {tuple(pair): k for k, pair in enumerate(model["merges"])}
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in plain]
        self.stand_in = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}
        self.special = regex.compile("|".join(regex.escape(t["content"]) for t in file["added_tokens"]) or r"(?!)")
        self.words = regex.compile(_WORDS)

    def symbols(self, word: str) -> list[str]:
        found = [self.stand_in[b] for b in word.encode("utf-8", "surrogatepass")]
        found[-1] += self.ending
        return [x for x in found if x in self.known]

    def merged(self, symbols: list[str]) -> int:
        """Number of symbols left when no rule applies any more."""
        n, rank = len(symbols), self.rank
        after, before = [*range(1, n), -1], [*range(-1, n - 1)]
        heap = [(r, i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (r := rank.get((symbols[i], symbols[i + 1]))) is not None]
        heapq.heapify(heap)
        merges = 0
        while heap:
            _, i, left, right = heapq.heappop(heap)
            j = after[i]
            if j < 0 or symbols[i] != left or symbols[j] != right:
                continue
            merges += 1
            symbols[i], symbols[j] = left + right, ""
            k = after[i] = after[j]
            after[j] = -1
            if k >= 0:
                before[k] = i
                if (r := rank.get((symbols[i], symbols[k]))) is not None:
                    heapq.heappush(heap, (r, i, symbols[i], symbols[k]))
            h = before[i]
            if h >= 0 and (r := rank.get((symbols[h], symbols[i]))) is not None:
                heapq.heappush(heap, (r, h, symbols[h], symbols[i]))
        return n - merges

    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE:
            self.clear()
        self[word] = n = self.merged(self.symbols(word))
        return n

    def _plain(self, text: str) -> int:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")
        return sum(map(self.__getitem__, self.words.findall(text.lower())))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if "<|" not in text:
            return self._plain(text)
        parts = self.special.split(text)
        return len(parts) - 1 + sum(map(self._plain, parts))


def counter(content: bytes) -> TokenCounter:
    key = hashlib.sha256(content).hexdigest()
    if key not in _COUNTERS:
        _COUNTERS[key] = TokenCounter(content)
    return _COUNTERS[key]


def token_counts(docs: DataFrame, tokenizer: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every row of a (doc_id, text) table."""
    held = prepare(docs.sparkSession).sparkContext.broadcast(Path(tokenizer).read_bytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(held.value).count
        for batch in batches:
            tokens = pa.array([count(text.as_py()) for text in batch.column(1)], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), tokens, batch.column(2)], ["doc_id", "n_tokens", "n_bytes"])

    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")
    counted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", size).mapInArrow(run, "doc_id long, n_tokens long, n_bytes long")
    return counted.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
