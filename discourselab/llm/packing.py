"""Packing documents into token sequences by exact complements.

Whether pieces fill a sequence depends on their lengths alone, so the plan is made on the histogram of
lengths (``CAPACITY`` entries whatever the corpus). An index keeps, by sum, how many single lengths, pairs
and triples of available lengths add up to it, and follows the counts as they fall:

    1. For each length, largest first, the gap it leaves is looked up, and a combination that fills it exactly
       is consumed as often as the counts allow; a look-up prefers one length to two and two to three, and
       large ones. Combinations of large lengths go first (``FLOORS``): small ones fit anywhere.
    2. Lengths of ``SMALL`` or more that are left are placed by best fit, longest first. The gaps of these
       sequences are looked up among the small lengths in the same way; best fit places what remains.
    3. Sequences that are not full share too few small pieces on small tables. So the fillings of most parts
       are released, one, two, four ... times as many as there are sequences that are not full, and packed
       anew with those by best fit; the fewest sequences win, and of these the fewest released.

A plan is a short list of fillings with multiplicities; pieces find their place by their rank among pieces
of their length, without ever being gathered.

Only documents longer than a sequence are cut, into full sequences; the first piece takes the remainder.

Scale
    One pass tokenises and writes small rows (no text). Ranks come from counts by (length, task) and a
    running sum over those counts. The driver sees the histogram; the broadcast plan is bounded by it.

Defined cases
    Null and empty texts are one piece that holds the end id alone. Repeated rows are packed each. An
    empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
import zlib
from collections import Counter
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from discourselab.session import cut, prepare

CAPACITY = 1024
END_ID = 2
#: The smallest lengths that combinations may use, pass by pass; lengths under the last are small.
FLOORS = (340, 200, 128)
SMALL = FLOORS[-1]
#: How a byte-level tokenizer file cuts a text before merging (a fixed value of such files).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

_ENCODERS: dict[str, object] = {}


def _byte_of() -> dict[str, int]:
    """The printable stand-ins that byte-level tokenizer files use for bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def encoder(content: bytes):
    """Encoder for the content of a byte-level tokenizer file whose ids are in merge order."""
    key = hashlib.sha256(content).hexdigest()
    if key not in _ENCODERS:
        import tiktoken

        file, back = json.loads(content), _byte_of()
        special = {t["content"]: t["id"] for t in file["added_tokens"]}
        ranks = {bytes(back[c] for c in token): i for token, i in file["model"]["vocab"].items() if token not in special}
        _ENCODERS[key] = tiktoken.Encoding(key, pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=special)
    return _ENCODERS[key]


def token_ids(text: str | None, encoding) -> np.ndarray:
    """Ids of a text and the end id; special strings inside it are their own tokens."""
    ids = encoding.encode_to_numpy(text or "", allowed_special="all", disallowed_special=())
    return np.append(ids, np.uint32(END_ID)).astype("<u4", copy=False)


def cuts(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, end) of the pieces of n ids."""
    first = n % capacity or capacity
    return [(0, min(first, n))] + [(at, at + capacity) for at in range(first, n, capacity)]


def _piece_batches(held):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, rank = TaskContext.get().partitionId(), np.zeros(CAPACITY + 1, np.int64)
        encoding = encoder(held.value)
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = token_ids(text.as_py(), encoding)
                for k, (a, b) in enumerate(cuts(len(ids))):
                    out.append((doc, k, a, b - a, zlib.crc32(ids[a:b].tobytes()), task, int(rank[b - a])))
                    rank[b - a] += 1
            columns = zip(*out, strict=True) if out else [[]] * 7
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(c), t) for c, t in zip(columns, kinds, strict=True)],
                ["doc_id", "piece", "start", "length", "ids_crc32", "task", "rank"],
            )

    return run


def pieces(docs: DataFrame, tokenizer: str) -> DataFrame:
    spark = prepare(docs.sparkSession)
    held = spark.sparkContext.broadcast(Path(tokenizer).read_bytes())
    return (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        .mapInArrow(_piece_batches(held), "doc_id long, piece int, start long, length long, ids_crc32 long, task int, rank long")
    )


Filling = tuple[int, list[tuple[int, int]]]


class Sums:
    """Index from a sum to the single lengths, pairs and triples of available lengths that add up to it.

    ``one``, ``two`` and ``three`` count ordered combinations by sum; when the last piece of a length is
    taken, its combinations leave all three.
    """

    def __init__(self, counts: np.ndarray) -> None:
        self.counts = counts.copy()
        self.one = (self.counts > 0).astype(np.int64)
        self.two = np.convolve(self.one, self.one)[: len(counts)]
        self.three = np.convolve(self.two, self.one)[: len(counts)]

    def _moved(self, values: np.ndarray, by: int) -> np.ndarray:
        out = np.zeros_like(values)
        out[by:] = values[: max(0, len(values) - by)]
        return out

    def take(self, lengths: Counter, times: int) -> None:
        """Take each length as often as it stands in ``lengths``, ``times`` over."""
        for x, copies in lengths.items():
            self.counts[x] -= copies * times
            if not self.counts[x]:  # (f - x)^2 and (f - x)^3, with f the sum over available lengths
                unit = self._moved(np.eye(1, len(self.one), dtype=np.int64)[0], x)
                self.three += 3 * (self._moved(self.one, 2 * x) - self._moved(self.two, x)) - self._moved(unit, 2 * x)
                self.two += self._moved(unit, x) - 2 * self._moved(self.one, x)
                self.one[x] = 0

    def times(self, lengths: Counter) -> int:
        """How often a combination is there."""
        return min(int(self.counts[x]) // copies for x, copies in lengths.items())

    def find(self, gap: int, own: int = 0) -> Counter | None:
        """Lengths that fill a gap exactly beside one piece of length ``own``; with it, and none larger."""
        held = [own] if own else []
        if gap == 0:
            return Counter(held)
        for found in self._combinations(gap, own or gap):
            if self.times(lengths := Counter([*held, *found])):
                return lengths
        return None

    def _combinations(self, gap: int, top: int) -> Iterator[tuple[int, ...]]:
        if gap <= top and self.one[gap]:
            yield (gap,)
        yield from self._pairs(gap, top)
        if self.three[gap]:
            x = np.arange(min(gap - 2, top), (gap - 1) // 3, -1)
            for first in x[(self.one[x] > 0) & (self.two[gap - x] > 0)].tolist():
                for pair in self._pairs(gap - first, first):
                    yield (first, *pair)

    def _pairs(self, total: int, top: int) -> Iterator[tuple[int, int]]:
        if self.two[total]:
            y = np.arange(min(total - 1, top), (total - 1) // 2, -1)
            for first in y[(self.one[y] > 0) & (self.one[total - y] > 0)].tolist():
                yield first, total - first


def _is_full(filling: list[tuple[int, int]], capacity: int) -> bool:
    return sum(length * copies for length, copies in filling) == capacity


def _sequences(fillings: list[Filling]) -> int:
    return sum(times for times, _ in fillings)


def _exact(counts: np.ndarray, capacity: int) -> list[Filling]:
    """Fillings by exact complements of all lengths in ``counts``, largest first; what is left stays there."""
    sums, fillings = Sums(counts), []
    for length in range(capacity, 0, -1):
        while sums.counts[length] and (lengths := sums.find(capacity - length, length)):
            times = sums.times(lengths)
            sums.take(lengths, times)
            fillings.append((times, list(lengths.items())))
    counts[:] = sums.counts
    return fillings


def _close_gaps(opened: list[Filling], small: np.ndarray, capacity: int) -> list[Filling]:
    """Fillings whose gaps small lengths fill exactly are closed; those that they cannot fill stay as they are."""
    sums, fillings = Sums(small), []
    for times, filling in sorted(opened, key=lambda x: -sum(length * copies for length, copies in x[1])):
        gap = capacity - sum(length * copies for length, copies in filling)
        while gap and times and (lengths := sums.find(gap)):
            some = min(times, sums.times(lengths))
            sums.take(lengths, some)
            fillings.append((some, filling + list(lengths.items())))
            times -= some
        if times:
            fillings.append((times, filling))
    small[:] = sums.counts
    return fillings


def _best_fit(counts: np.ndarray, capacity: int, opened: list[Filling] = ()) -> list[Filling]:
    """Best fit, longest first, of equal pieces at once: the tightest open gap takes as many as go in."""
    gaps: dict[int, list[Filling]] = {}
    for times, filling in opened:
        gaps.setdefault(capacity - sum(length * copies for length, copies in filling), []).append((times, filling))
    for length in np.flatnonzero(counts)[::-1].tolist():
        left = int(counts[length])
        while left:
            gap = min((g for g in gaps if g >= length), default=capacity)
            times, filling = gaps[gap].pop() if gap in gaps else (-(-left // (capacity // length)), [])
            if gap in gaps and not gaps[gap]:
                del gaps[gap]
            copies = min(gap // length, left)
            whole = min(times, left // copies)
            gaps.setdefault(gap - copies * length, []).append((whole, [*filling, (length, copies)]))
            if filling and times > whole:
                gaps.setdefault(gap, []).append((times - whole, filling))
            left -= whole * copies
    return [x for held in gaps.values() for x in held]


def _released(full: list[Filling], rest: list[Filling], capacity: int) -> list[Filling]:
    """Full fillings of most parts are packed anew with those that are not full, where that saves sequences."""
    full = sorted(full, key=lambda x: sum(copies for _, copies in x[1]))
    parted = sum(times for times, filling in full if filling != [(capacity, 1)])
    best, release = full + rest, 0
    while release < parted and rest:
        release = min(parted, 2 * release or _sequences(rest))
        counts, kept, wanted = np.zeros(capacity + 1, np.int64), [], release
        for times, filling in full[::-1]:
            some = min(times, wanted)
            wanted -= some
            for length, copies in filling:
                counts[length] += some * copies
            if times > some:
                kept.append((times - some, filling))
        for times, filling in rest:
            for length, copies in filling:
                counts[length] += times * copies
        found = kept + _best_fit(counts, capacity)
        best = min(best, found, key=_sequences)
    return best


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[Filling]:
    """(how often, [(length, copies), ...]) fillings that place every piece of a histogram of lengths."""
    counts = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        counts[length] = n
    fillings: list[Filling] = []
    for floor in FLOORS:
        part = counts.copy()
        part[:floor] = 0
        fillings += _exact(part, capacity)
        counts[floor:] = part[floor:]
    large, small = counts.copy(), counts.copy()
    large[:SMALL], small[SMALL:] = 0, 0
    closed = _close_gaps(_best_fit(large, capacity), small, capacity)
    fillings += _best_fit(small, capacity, closed)
    full = [x for x in fillings if _is_full(x[1], capacity)]
    return _released(full, [x for x in fillings if not _is_full(x[1], capacity)], capacity)


def slots(fillings: list[Filling]) -> dict[int, np.ndarray]:
    """By length, rows (first rank, copies, first sequence, offset): where the pieces of each rank go."""
    rows: dict[int, list[tuple[int, int, int, int]]] = {}
    ranks: dict[int, int] = {}
    sequence = 0
    for times, filling in fillings:
        offset = 0
        for length, copies in filling:
            rank = ranks.get(length, 0)
            rows.setdefault(length, []).append((rank, copies, sequence, offset))
            ranks[length] = rank + times * copies
            offset += copies * length
        sequence += times
    return {length: np.array(x, np.int64) for length, x in rows.items()}


def pack(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece."""
    cutting = cut(pieces(docs, tokenizer))
    by_task = cutting.groupBy("length", "task").agg(F.count("*").alias("n"))
    histogram = {r.length: r.n for r in by_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    held = docs.sparkSession.sparkContext.broadcast(slots(plan(histogram)))
    running = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    before = by_task.select("length", "task", F.coalesce(F.sum("n").over(running), F.lit(0)).alias("before"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(x).to_numpy(zero_copy_only=False) for x in ("length", "rank"))
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for x in np.unique(length).tolist():
                rows, mine = held.value[x], np.flatnonzero(length == x)
                row = rows[np.searchsorted(rows[:, 0], rank[mine], "right") - 1]
                inside = rank[mine] - row[:, 0]
                sequence[mine] = row[:, 2] + inside // row[:, 1]
                offset[mine] = row[:, 3] + inside % row[:, 1] * x
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    ranked = cutting.join(before, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") + F.col("before")).alias("rank"))
    return ranked.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
