"""Repeated passages: run-length compressed Burrows-Wheeler index and matching statistics.

A byte is removed if it lies in a 50-byte string that also starts in a document with a smaller id. What a
position matches is read off an index of the text it could match: the Burrows-Wheeler transform of the text
in run-compressed form, with the suffix positions at run ends sampled. Streaming the text along the samples
gives every position its neighbour in suffix order and the matching statistic with it; statistics of 50 or
more chain equal 50-byte strings together, and the smallest document of a chain holds the string first.

Bringing the text together
    A 50-byte string is dealt by its anchor, the leftmost smallest hash among its 16-byte substrings. Equal
    strings have equal anchors, so no match is lost; a maximal run of strings with one anchor is a segment.
    Of the string at least 17 bytes lie on one side of the anchor, so equal strings agree on a side, too.

    1. Anchors of all texts meet in shards as packed numbers; those that two different texts at least hold
       with a side alike are shared. Sides that a sample finds very common skip this and count as shared.
    2. The first document of every distinct text cuts out its segments with shared anchors.
    3. Equal segments fold into one with the smallest doc_id on the map side; each shard of different
       segments builds its index and streams them. Anchors that by the sample have more than ``HOT``
       different segments (a phrase in ever new surroundings) are cut finer: each 50-byte string is a
       segment of its own, dealt by its own hash.
    4. Owners found for segments return to the places where they stand and become spans. A copy of an
       earlier document's whole text is one span.

Scale
    Exact at any size: the anchors only decide what has to be looked at. Shards follow the size of the
    corpus, no group of copies meets in one task (very common sides are not gathered, equal segments are
    folded before the shuffle, places join by key). A shard beyond ``PART`` bytes is indexed in parts, dealt
    by 50-byte string, so the memory of an index has a bound whatever meets in a shard. The driver holds
    the lists of very common sides and of hot anchors only, bounded by the sample.

Defined cases
    Null text counts as empty. Texts under 50 bytes keep everything. Spans belong to a doc_id and a text, so
    rows of one doc_id with different texts are judged each; a doc_id is not smaller than itself, so they
    do not match one another, and repeated rows get equal results. Rows with a null doc_id come after all
    others in order: they match those and not one another. An empty table gives an empty result. Other
    columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from discourselab.session import cut, discard, prepare, scratch

LENGTH = 50
GRAM = 16
#: Of 50 equal bytes around an anchor this many lie on one of its sides.
SIDE = (LENGTH - GRAM) // 2
#: Bytes of text that a shard of anchors, and a shard of segments, stand for.
ANCHOR_SHARD, SEGMENT_SHARD = 16_000_000, 2_000_000
#: Different segments with one anchor beyond which they are dealt by 50-byte string: about a shard's fill.
HOT = 20_000
#: Bytes of segments that are indexed at once.
PART = 16_000_000
#: Documents in the sample that finds very common sides, and how many of them make a side one.
SAMPLE_LEAST, SAMPLE_MOST, SAMPLE_SHARE, COMMON = 4000, 200_000, 1000, 8
_CHUNK = 2_000_000
_LAST = (1 << 63) - 1
_PLACE = np.uint64((1 << 24) - 1)
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)]
_TABLE = np.random.default_rng(50).integers(1 << 63, size=256, dtype=np.uint64)


def _hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all 8-byte and all ``GRAM``-byte substrings, by doubling."""
    h = _TABLE[data]
    for k, step in enumerate((1, 2, 4, 8)):
        eight = h
        h = h[:-step] * _MIX[k % 3] + h[step:]
        h ^= h >> np.uint64(31 - k)
    h *= _MIX[2]
    return eight, h ^ h >> np.uint64(28)


class Segments:
    """Segments of some texts: parallel arrays over all of them, in order.

    hash        of the anchor
    text        number of the text
    start       first window, in its text
    windows     how many windows
    right, left hashes of the anchor with ``SIDE`` more bytes on one side, 0 where the text ends before
    ends        hash of the first and last ``GRAM`` bytes and of how many windows there are
    """

    def __init__(self, texts: list[bytes]) -> None:
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        total = int(sizes.sum())
        self.hash = self.right = self.left = self.ends = np.empty(0, np.uint64)
        self.text = self.start = self.windows = np.empty(0, np.int64)
        if total < LENGTH:
            return
        eight, gram = _hashes(np.frombuffer(b"".join(texts), np.uint8))
        # leftmost smallest: the position fills the low bits
        low, reach, width = gram & ~_PLACE | np.arange(len(gram), dtype=np.uint64), 1, LENGTH - GRAM + 1
        while reach * 2 <= width:
            low, reach = np.minimum(low[:-reach], low[reach:]), reach * 2
        if width > reach:
            low = np.minimum(low[: reach - width], low[width - reach :])
        ends = np.cumsum(sizes)
        begins, windows = ends - sizes, np.maximum(0, sizes - LENGTH + 1)
        mark = np.zeros(total + 1, np.int32)
        np.add.at(mark, begins[windows > 0], 1)
        np.add.at(mark, (begins + windows)[windows > 0], -1)
        change = np.ones(len(low), bool)
        change[1:] = low[1:] != low[:-1]
        change[begins[windows > 0]] = True
        starts = np.flatnonzero((np.cumsum(mark[: len(low)]) > 0) & change)
        self.text = np.searchsorted(ends, starts, "right")
        place = (low[starts] & _PLACE).astype(np.int64)
        self.hash = gram[place]
        self.start = starts - begins[self.text]
        self.windows = np.minimum(np.append(starts[1:], total), (begins + windows)[self.text]) - starts
        self.right = self._side(eight, place + GRAM, place + GRAM + SIDE <= ends[self.text], 0)
        self.left = self._side(eight, place - SIDE, place - SIDE >= begins[self.text], 1)
        self.ends = (gram[starts] * _MIX[0] ^ gram[starts + self.windows + LENGTH - 1 - GRAM]) * _MIX[1] + self.windows.astype(np.uint64)

    def _side(self, eight: np.ndarray, place: np.ndarray, inside: np.ndarray, k: int) -> np.ndarray:
        """Hash of the anchor and the ``SIDE`` bytes at ``place``, from overlapping 8-byte hashes."""
        x = self.hash
        for step in (*range(0, SIDE - 8, 8), SIDE - 8):
            x = (x ^ x >> np.uint64(29)) * _MIX[k] + eight[np.clip(place + step, 0, len(eight) - 1)]
        x ^= x >> np.uint64(30)
        x *= _MIX[2]
        return np.where(inside, (x ^ x >> np.uint64(27)) | np.uint64(1), np.uint64(0))


def _chunks(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, list[bytes]]]:
    """(numbers, offsets, parts) of about ``_CHUNK`` bytes; a longer text comes in parts that overlap."""
    number, offset, parts, size = [], [], [], 0
    for k, text in enumerate(texts):
        for at in range(0, max(1, len(text) - LENGTH + 1), _CHUNK):
            part = text[at : at + _CHUNK + LENGTH - 1] if len(text) > _CHUNK else text
            number.append(k)
            offset.append(at)
            parts.append(part)
            size += len(part)
            if size >= _CHUNK:
                yield np.array(number), np.array(offset), parts
                number, offset, parts, size = [], [], [], 0
    if parts:
        yield np.array(number), np.array(offset), parts


def _bytes(text: pa.Scalar) -> bytes:
    return (text.as_py() or "").encode("utf-8", "surrogatepass")


def _among(known: np.ndarray, keys: np.ndarray) -> np.ndarray:
    if not len(known):
        return np.zeros(len(keys), bool)
    at = np.searchsorted(known, keys)
    at[at == len(known)] = 0
    return known[at] == keys


def _unique(columns: list[np.ndarray]) -> list[np.ndarray]:
    """Different rows of some columns."""
    order = np.lexsort(columns)
    columns = [x[order] for x in columns]
    fresh = np.append(True, np.any([x[1:] != x[:-1] for x in columns], axis=0))[: len(order)]
    return [x[fresh] for x in columns]


def _common(docs: DataFrame, rows: int, hot_limit: int) -> tuple[np.ndarray, np.ndarray]:
    """From a sample: sides of anchors that ``COMMON`` documents hold, and hot anchors; both sorted.

    An anchor is hot if its different segments in the sample stand for more than ``hot_limit`` in all.
    """
    share = min(1.0, max(SAMPLE_LEAST, min(SAMPLE_MOST, rows / SAMPLE_SHARE)) / max(1, rows))
    draw = F.pmod(F.xxhash64(F.lit("anchors"), F.col("doc_id")), F.lit(1 << 30)) / float(1 << 30)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [_bytes(x) for x in batch.column(0)]
            for number, _, parts in _chunks(texts):
                s = Segments(parts)
                _, side = _unique([np.tile(number[s.text], 2), np.concatenate([s.right, s.left])])
                side = side[side != 0]
                ends, anchor = _unique([s.ends, s.hash])
                h, kind = np.concatenate([side, anchor]), np.concatenate([np.zeros(len(side), np.uint64), ends | np.uint64(1)])
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(kind.view(np.int64))], ["h", "kind"])

    held = docs.where(draw < share).select("text").mapInArrow(run, "h long, kind long").groupBy("h", "kind").agg(F.count("*").alias("n"))
    sides = held.where((F.col("kind") == 0) & (F.col("n") >= COMMON)).select("h", F.lit(True).alias("side"))
    kinds = held.where("kind <> 0").groupBy("h").agg(F.count("*").alias("n"))
    hot = kinds.where(F.col("n") >= max(COMMON, hot_limit * share)).select("h", F.lit(False).alias("side"))
    found = sides.unionByName(hot).collect()
    return tuple(np.sort(np.array([r.h for r in found if r.side == side], np.int64).view(np.uint64)) for side in (True, False))


def _checks(side: np.ndarray) -> np.ndarray:
    """Two bytes of each side; 0 stands for a side that is not there."""
    return np.where(side == 0, np.uint64(0), (side >> np.uint64(20)) % np.uint64(65535) + np.uint64(1)).astype(np.uint16)


def _deal(common, shards: int):
    """Rows (shard, payload): for each text its key, how many anchors it has there, their low halves and sides.

    Sides known to be common are blanked; an anchor with no side left is not sent.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            found = []
            for number, _, parts in _chunks([_bytes(x) for x in batch.column(1)]):
                s = Segments(parts)
                right, left = (np.where(_among(common.value[0], x), 0, _checks(x)).astype(np.uint16) for x in (s.right, s.left))
                send = (right > 0) | (left > 0)
                found.append((s.hash[send], number[s.text[send]], right[send], left[send]))
            h, owner, right, left = (np.concatenate(x) for x in zip(*found, strict=True)) if found else [np.empty(0, np.uint64)] * 4
            if not len(h):
                continue
            shard = (h >> np.uint64(32)).astype(np.int64) % shards
            order = np.lexsort((owner, shard))
            low, owner, right, left, shard = h[order].astype(np.uint32), owner[order], right[order], left[order], shard[order]
            cut = np.append(0, np.flatnonzero(np.diff(shard)) + 1)
            payloads = []
            for a, b in zip(cut.tolist(), np.append(cut[1:], len(low)).tolist(), strict=True):
                texts_here, n = np.unique(owner[a:b], return_counts=True)
                payloads.append(
                    np.uint32(len(n)).tobytes() + keys[
                        texts_here
                    ].tobytes() + n.astype(np.uint32).tobytes() + low[a:b].tobytes() + right[a:b].tobytes() + left[a:b].tobytes()
                )
            yield pa.RecordBatch.from_arrays([pa.array(shard[cut].astype(np.int32)), pa.array(payloads, pa.binary())], ["shard", "payload"])

    return run


def _held_by_two(low: np.ndarray, check: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Which entries have another text with the same anchor and side."""
    side = low.astype(np.int64) << 16 | check
    order = np.argsort(side, kind="stable")
    side, key = side[order], key[order]
    first = np.flatnonzero(np.append(True, side[1:] != side[:-1]))
    two = np.repeat(np.maximum.reduceat(key, first) != np.minimum.reduceat(key, first), np.diff(np.append(first, len(side))))
    out = np.empty(len(side), bool)
    out[order] = two
    return out & (check > 0)


def _shared_in_shard(buckets: int):
    """Rows (bucket, payload) of a shard: anchors that two different texts hold with one side alike, by text.

    Of 50 equal bytes around a 16-byte anchor, 17 at least lie on one side of it. Texts are dealt to
    buckets by their key, so the rows are as many as shards and buckets and not as texts and shards.
    """

    def run(group: pa.Table) -> pa.Table:
        key, anchor = _shared(group)
        bucket = key.view(np.uint64) % np.uint64(buckets)
        order = np.argsort(bucket, kind="stable")
        key, anchor, bucket = key[order], anchor[order], bucket[order].astype(np.int32)
        cut = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))[: len(bucket)]
        ends = np.append(cut[1:], len(key))[: len(cut)]
        payloads = [np.concatenate([key[a:b], anchor[a:b]]).tobytes() for a, b in zip(cut.tolist(), ends.tolist(), strict=True)]
        return pa.table({"bucket": pa.array(bucket[cut]), "payload": pa.array(payloads, pa.binary())})

    return run


def _lists_of_bucket(group: pa.Table) -> pa.Table:
    """(key, anchors): the shared anchors of every text of a bucket."""
    parts = [np.frombuffer(x.as_buffer(), np.int64).reshape(2, -1) for x in group.column("payload")]
    key, anchor = np.concatenate(parts, axis=1)
    order = np.argsort(key, kind="stable")
    key, anchor = key[order], anchor[order]
    begin = np.flatnonzero(np.append(True, key[1:] != key[:-1]))[: len(key)]
    lists = pa.LargeListArray.from_arrays(pa.array(np.append(begin, len(key))), pa.array(anchor)).cast(pa.list_(pa.int64()))
    return pa.table({"key": pa.array(key[begin]), "anchors": lists})


def _shared(group: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(text key, anchor) of the shared anchors of a shard, each once for a text."""
    shard, keys, lows, rights, lefts = group.column("shard")[0].as_py(), [], [], [], []
    for payload in group.column("payload"):
        data = payload.as_buffer()
        n = int(np.frombuffer(data, np.uint32, 1)[0])
        key, count = np.frombuffer(data, np.int64, n, 4), np.frombuffer(data, np.uint32, n, 4 + 8 * n)
        m, at = int(count.sum()), 4 + 12 * n
        keys.append(np.repeat(key, count))
        lows.append(np.frombuffer(data, np.uint32, m, at))
        rights.append(np.frombuffer(data, np.uint16, m, at + 4 * m))
        lefts.append(np.frombuffer(data, np.uint16, m, at + 6 * m))
    key, low, right, left = (np.concatenate(x) for x in (keys, lows, rights, lefts))
    shared = _held_by_two(low, right, key) | _held_by_two(low, left, key)
    key, low = key[shared], low[shared]
    order = np.lexsort((low, key))
    key, low = key[order], low[order]
    fresh = np.append(True, (key[1:] != key[:-1]) | (low[1:] != low[:-1]))[: len(key)]
    return key[fresh], (np.int64(shard) << 32) + low[fresh].astype(np.int64)


def _cut_out(common, anchor_shards: int):
    """Rows (anchor, doc_id, key, start, seg) of the segments with shared anchors of compressed texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            doc_ids, keys = (batch.column(x).to_numpy(zero_copy_only=False) for x in ("doc_id", "key"))
            texts = [unpack(x.as_buffer()) for x in batch.column("packed")]
            listed = batch.column("anchors")
            for number, offset, parts in _chunks(texts):
                s = Segments(parts)
                if not len(s.hash):
                    continue
                who = number[s.text]
                own = ((s.hash >> np.uint64(32)).astype(np.int64) % anchor_shards << 32) + (s.hash & np.uint64(0xFFFFFFFF)).astype(np.int64)
                sides, hot = common.value
                take = _among(sides, s.right) | _among(sides, s.left)
                edges = np.searchsorted(who, np.arange(number[0], number[-1] + 2))
                for k, (a, b) in enumerate(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True), int(number[0])):
                    if a < b and listed[k].is_valid:
                        take[a:b] |= np.isin(own[a:b], listed[k].values.to_numpy())
                text, start, windows, anchor = s.text[take], s.start[take], s.windows[take], s.hash[take].view(np.int64)
                if (fine := _among(hot, s.hash[take])).any():
                    times = np.where(fine, windows, 1)
                    first = np.cumsum(times) - times
                    text, anchor, start = (
                        np.repeat(text, times), np
                        .repeat(anchor, times), np
                        .repeat(start - first, times) + np
                        .where(np.repeat(fine, times), np.arange(times.sum()), np.repeat(first, times))
                    )
                    windows, fine = np.repeat(np.where(fine, 1, windows), times), np.repeat(fine, times)
                    anchor[fine] = [xxhash.xxh64_intdigest(parts[o][i : i + LENGTH]) >> 1 for o, i in zip(text[fine].tolist(), start[fine].tolist(), strict=True)]
                segs = [parts[o][i : i + w + LENGTH - 1] for o, i, w in zip(text.tolist(), start.tolist(), windows.tolist(), strict=True)]
                columns = [anchor, doc_ids[number[text]], keys[number[text]], (start + offset[text]).astype(np.int32)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.array(segs, pa.binary())], ["anchor", "doc_id", "key", "start", "seg"])

    return run


class RunIndex:
    """Run-length compressed Burrows-Wheeler transform of some strings, each closed by its own end mark.

    A run is a block of rows, in suffix order, with one preceding byte (before a string's first byte stands an
    end mark of its own). Kept are the first row of every run (``run_start``), its byte (``run_char``, 0 for an
    end mark) and samples: the position of the suffix at its last row (``run_end``) and, in text order,
    positions ``at`` that head a run, the position ``above`` of the suffix one row up (the end of the run
    before) and how many bytes the two share. Nothing is kept by row or by position.
    """

    def __init__(self, strings: list[bytes]) -> None:
        self.sizes = sizes = np.fromiter(map(len, strings), np.int64, len(strings))
        raw = np.frombuffer(b"".join(x + b"\0" for x in strings) + bytes(8), np.uint8)
        n = len(raw) - 8
        ends = np.cumsum(sizes + 1) - 1
        self.begins = ends - sizes
        left = np.repeat(ends, sizes + 1) - np.arange(n)  # bytes from here to the string's end
        kinds = np.flatnonzero(np.bincount(raw[:n], minlength=256))
        number = np.zeros(256, np.uint64)
        number[kinds] = np.arange(1, len(kinds) + 1)
        code = np.where(left > 0, number[raw[:n]], 0).astype(np.uint64)
        order = self._suffix_order(code, int(len(kinds)).bit_length(), left, int(sizes.max(initial=0)))
        preceding = np.zeros(n, np.uint64)
        preceding[1:] = code[:-1]
        before = preceding[order]
        self.run_start = np.flatnonzero(np.append(True, (before[1:] != before[:-1]) | (before[1:] == 0))[:n])
        self.run_char = before[self.run_start]
        self.run_end = order[np.append(self.run_start[1:], n)[: len(self.run_start)] - 1]
        heads = order[self.run_start]
        above = np.append(heads[:1], self.run_end[:-1])  # nothing is above the first row
        shared = np.minimum(self._shared(raw, heads, above), np.minimum(left[heads], left[above]))
        shared[:1] = 0
        sort = np.argsort(heads)
        self.at, self.above, self.shared = heads[sort], above[sort], shared[sort]

    @classmethod
    def _suffix_order(cls, code: np.ndarray, bits: int, left: np.ndarray, longest: int) -> np.ndarray:
        """Positions in the order of their suffixes, by ranks of doubled or tripled prefixes."""
        place = int(len(code)).bit_length()
        reach = min(64 // max(1, bits), max(1, (64 - place) // max(1, bits)))
        key = np.zeros(len(code), np.uint64)
        for k in range(reach):
            key = key << np.uint64(bits) | cls._beyond(code, k, left)
        rank, order, kinds = cls._ranks(key, reach * bits, place)
        while reach < longest:
            bits = kinds.bit_length()
            parts = 3 if 3 * bits + place <= 64 else 2
            key = rank.astype(np.uint64)
            for k in range(1, parts):
                key = key << np.uint64(bits) | cls._beyond(rank + 1, k * reach, left)
            rank, order, kinds = cls._ranks(key, parts * bits, place)
            reach *= parts
        return order

    @staticmethod
    def _beyond(values: np.ndarray, step: int, left: np.ndarray) -> np.ndarray:
        """The values ``step`` positions on, 0 where the string has ended."""
        out = np.zeros(len(values), np.uint64)
        if step < len(values):
            out[: len(values) - step] = values[step:]
        out[left <= step] = 0
        return out

    @staticmethod
    def _ranks(key: np.ndarray, bits: int, place: int) -> tuple[np.ndarray, np.ndarray, int]:
        """Rank of every key, the positions in order (by position at a tie), and how many ranks there are."""
        if bits + place <= 64:  # one number holds key and position
            both = np.sort(key << np.uint64(place) | np.arange(len(key), dtype=np.uint64))
            order, key = (both & np.uint64((1 << place) - 1)).astype(np.int64), both >> np.uint64(place)
        else:
            order = np.argsort(key, kind="stable")
            key = key[order]
        steps = np.zeros(len(key), np.int32)
        np.cumsum(key[1:] != key[:-1], out=steps[1:])
        rank = np.empty(len(key), np.int32)
        rank[order] = steps
        return rank, order, int(steps[-1]) + 1 if len(steps) else 0

    @staticmethod
    def _shared(raw: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """How many bytes from positions a and b on are equal, in steps of eight at least to the first that differs."""
        words = np.ndarray(len(raw) - 7, "<u8", raw, strides=(1,))
        out, todo, at = np.zeros(len(a), np.int64), np.flatnonzero(a != b), 0
        while len(todo):
            todo = todo[np.maximum(a[todo], b[todo]) + at < len(words)]
            differ = words[a[todo] + at] ^ words[b[todo] + at]
            lowest = differ & (~differ + np.uint64(1))  # the first bit that differs
            out[todo] += np.where(differ == 0, 64, np.bitwise_count(lowest - np.uint64(1))) // 8
            todo, at = todo[differ == 0], at + 8
        return out

    def streamed(self) -> tuple[np.ndarray, np.ndarray]:
        """For every position: that of the suffix one row up, and the matching statistic with it.

        One step on in the text keeps two neighbours neighbours, and takes a byte off what they share, unless
        a run starts between them; so a position reads both off the last sample before it.
        """
        gaps = np.diff(np.append(self.at, int((self.sizes + 1).sum())))
        steps = np.arange(int(gaps.sum())) - np.repeat(self.at, gaps)
        return np.repeat(self.above, gaps) + steps, np.repeat(self.shared, gaps) - steps


def first_holders(strings: list[bytes], docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each string, by position, the smallest of ``docs`` over strings that hold its next 50 bytes.

    Flat, with the offset of each string. A matching statistic of 50 or more links a position to the one
    above it in suffix order; the chains of links are the classes of equal 50-byte strings.
    """
    index = RunIndex(strings)
    above, statistic = index.streamed()
    linked = np.flatnonzero(statistic >= LENGTH)
    root, todo = np.arange(len(above)), linked
    root[linked] = above[linked]
    while len(todo):  # chains are followed in doubling steps
        up = root[root[todo]]
        todo, last = todo[up != root[todo]], todo
        root[last] = up
    least = np.repeat(docs, index.sizes + 1)
    np.minimum.at(least, root[linked], least[linked])
    windows = np.maximum(0, index.sizes - LENGTH + 1)
    offsets = np.concatenate(([0], np.cumsum(windows)))
    place = np.arange(offsets[-1]) + np.repeat(index.begins - offsets[:-1], windows)
    return least[root[place]], offsets


def bounded_holders(strings: list[bytes], docs: np.ndarray, part: int = PART) -> tuple[np.ndarray, np.ndarray]:
    """``first_holders`` by indexes of about ``part`` bytes at most; beyond that, each 50-byte string is dealt by its hash."""
    sizes = np.fromiter(map(len, strings), np.int64, len(strings))
    if sizes.sum() <= part:
        return first_holders(strings, docs)
    windows = np.maximum(0, sizes - LENGTH + 1)
    offsets = np.concatenate(([0], np.cumsum(windows)))
    name = np.concatenate([[xxhash.xxh32_intdigest(x[i : i + LENGTH]) for i in range(n)] for x, n in zip(strings, windows.tolist(), strict=True)])
    order, least = np.argsort(name, kind="stable"), np.empty(offsets[-1], np.int64)
    at, step = 0, max(1, part // (LENGTH + 1))
    while at < len(order):
        until = np.searchsorted(name[order], name[order[min(at + step, len(order)) - 1]], "right")  # equal names stay together
        mine = order[at:until]
        owner = np.searchsorted(offsets, mine, "right") - 1
        held = [strings[k][i : i + LENGTH] for k, i in zip(owner.tolist(), (mine - offsets[owner]).tolist(), strict=True)]
        number = {x: k for k, x in enumerate(dict.fromkeys(held))}
        which = np.fromiter(map(number.get, held), np.int64, len(held))
        first = np.full(len(number), _LAST)
        np.minimum.at(first, which, docs[owner])
        least[mine] = first_holders(list(number), first)[0][which]
        at = until
    return least, offsets


def _index_shard(group: pa.Table) -> pa.Table:
    """(a, b, starts, ends, holders) of the segments of a shard in which some document can match."""
    strings = group.column("seg").to_pylist()
    docs, copies = group.column("holder").to_numpy(), group.column("copies").to_numpy()
    found, offsets = bounded_holders(strings, docs)
    fresh = np.append(True, found[1:] != found[:-1])
    fresh[offsets[:-1]] = True
    starts = np.flatnonzero(fresh)
    ends = np.append(starts[1:], len(found))
    string = np.searchsorted(offsets, starts, "right") - 1
    some = (found[starts] < docs[string]) | (copies[string] > 1)
    starts, ends, string = starts[some], ends[some], string[some]
    begin = np.flatnonzero(np.append(True, string[1:] != string[:-1]))[: len(string)]
    lists = lambda x, kind: pa.LargeListArray.from_arrays(pa.array(np.append(begin, len(string))), pa.array(x.astype(kind))).cast(pa.list_(pa.from_numpy_dtype(kind)))
    base = offsets[string]
    names = {x: group.column(x).take(pa.array(string[begin])) for x in ("a", "b")}
    return pa.table(
        names | {"starts": lists(starts - base, np.int32), "ends": lists(ends - base + LENGTH - 1, np.int32), "holders": lists(found[starts], np.int64)}
    )


def _pack_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    pack = zstandard.ZstdCompressor(level=1).compress
    for batch in batches:
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array([pack(_bytes(x)) for x in batch.column(2)], pa.binary())],
            ["doc_id", "key", "packed"],
        )


def merged(spans: np.ndarray) -> np.ndarray:
    """Sorted rows (start, end) of the union of some spans that overlap or touch."""
    if not len(spans):
        return spans.reshape(0, 2)
    spans = spans[np.argsort(spans[:, 0], kind="stable")]
    reach = np.maximum.accumulate(spans[:, 1])
    first = np.append(True, spans[1:, 0] > reach[:-1])
    last = np.append(np.flatnonzero(first)[1:] - 1, len(spans) - 1)
    return np.stack([spans[first, 0], reach[last]], axis=1)


def _finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    unpack = zstandard.ZstdDecompressor().decompress
    for batch in batches:
        out = []
        for packed, copied, starts, ends in zip(*(batch.column(x) for x in ("packed", "copied", "starts", "ends")), strict=True):
            text = unpack(packed.as_buffer())
            if copied.as_py() and len(text) >= LENGTH:
                spans = np.array([[0, len(text)]])
            elif starts.is_valid:
                spans = merged(np.stack([starts.values.to_numpy(), ends.values.to_numpy()], axis=1))
            else:
                spans = np.empty((0, 2), np.int64)
            kept, at = [], 0
            for a, b in spans.tolist():
                kept.append(text[at:a])
                at = b
            kept.append(text[at:])
            out.append((len(text), int((spans[:, 1] - spans[:, 0]).sum()), len(spans), hashlib.sha256(b"".join(kept)).hexdigest()))
        columns = list(zip(*out, strict=True)) if out else [[]] * 4
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), *(pa.array(list(c), t) for c, t in zip(columns, kinds, strict=True))],
            ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"],
        )


@contextmanager
def _freed_shuffles(spark) -> Iterator[None]:
    """What is written inside frees its shuffle files when done: its result is durable and they are large."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def _names(column: str) -> list:
    """128 bits stand for a segment."""
    return [F.xxhash64(column).alias("a"), F.xxhash64(F.lit("other"), column).alias("b")]


_PLACES = "anchor long, doc_id long, key long, start int, seg binary"
_OWNERS = "a long, b long, starts array<int>, ends array<int>, holders array<bigint>"


def repeated_spans(docs: DataFrame, hot_limit: int = HOT) -> DataFrame:
    """(doc_id, key, copied, starts, ends) of the documents from which something is removed.

    ``key`` is the hash of a text; doc_id and key together stand for a row and its equals.
    """
    spark = prepare(docs.sparkSession)
    keyed = docs.select("doc_id", F.xxhash64("text").alias("key"), "text")
    sizes = cut(keyed.select("doc_id", "key", F.unhex(F.sha2("text", 256)).alias("sha"), F.octet_length("text").alias("size")))
    total = sizes.agg(F.sum("size").alias("size"), F.count("*").alias("rows")).first()
    shards, cuts = (max(1, -(-int(total["size"] or 0) // x)) for x in (ANCHOR_SHARD, SEGMENT_SHARD))
    common = spark.sparkContext.broadcast(_common(docs, int(total["rows"]), hot_limit))

    dealt = keyed.select("key", "text").mapInArrow(_deal(common, shards), "shard int, payload binary")
    shared = dealt.groupBy("shard").applyInArrow(_shared_in_shard(shards), "bucket int, payload binary")
    lists = shared.groupBy("bucket").applyInArrow(_lists_of_bucket, "key long, anchors array<bigint>")
    firsts = sizes.groupBy("sha", "key").agg(F.min("doc_id").alias("doc_id"))
    wanted = firsts.join(lists, "key", "left").select(F.col("doc_id").alias("_doc"), F.col("key").alias("_key"), "anchors")

    same_row = (F.col("doc_id") == F.col("_doc")) & (F.col("key") == F.col("_key"))
    packed = keyed.mapInArrow(_pack_texts, "doc_id long, key long, packed binary")
    cutting = packed.join(wanted, same_row).select("doc_id", "key", "packed", "anchors").mapInArrow(_cut_out(common, shards), _PLACES)
    held = scratch(spark, "repeats-places")
    with _freed_shuffles(spark):
        cutting.write.option("compression", "zstd").parquet(held)
    places = spark.read.schema(_PLACES).parquet(held)

    different = places.groupBy("anchor", "seg").agg(F.min("doc_id").alias("holder"), F.count("*").alias("copies"))
    shard = F.pmod("anchor", F.lit(cuts)).cast("int").alias("shard")
    owners = different.select(shard, *_names("seg"), "seg", "holder", "copies").groupBy("shard").applyInArrow(_index_shard, _OWNERS)
    # owners are one row a name, so the hashed side has no skew and the many places need no sort
    met = places.select("doc_id", "key", "start", *_names("seg")).join(owners.hint("shuffle_hash"), ["a", "b"])
    zipped = F.filter(F.arrays_zip("starts", "ends", "holders"), lambda x: x["holders"] < F.col("doc_id"))
    moved = F.transform(zipped, lambda x: F.struct((x["starts"] + F.col("start")).alias("s"), (x["ends"] + F.col("start")).alias("e")))
    found = met.select("doc_id", "key", moved.alias("x")).where(F.size("x") > 0)
    within = found.groupBy("doc_id", "key").agg(F.flatten(F.collect_list("x")).alias("x"))
    first = firsts.select("sha", F.col("doc_id").alias("first"))
    copies = sizes.join(first, "sha").where("doc_id > first").select("doc_id", "key").distinct()
    none = F.lit(None).cast("array<int>")
    spans = within.select("doc_id", "key", F.lit(False).alias("copied"), F.col("x.s").alias("starts"), F.col("x.e").alias("ends"))
    spans = spans.unionByName(copies.select("doc_id", "key", F.lit(True).alias("copied"), none.alias("starts"), none.alias("ends")))
    out = scratch(spark, "repeats-spans")
    with _freed_shuffles(spark):
        spans.write.parquet(out)
    discard(spark, held)
    return spark.read.schema(spans.schema).parquet(out)


def remove_repeats(docs: DataFrame, hot_limit: int = HOT) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 of every row of a (doc_id, text) table."""
    real = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    whole = real.select(F.coalesce("doc_id", F.lit(_LAST)).alias("doc_id"), "text")
    spans = repeated_spans(whole, hot_limit).withColumnsRenamed({"doc_id": "_doc", "key": "_key"})
    packed = whole.select("doc_id", F.xxhash64("text").alias("key"), "text").mapInArrow(_pack_texts, "doc_id long, key long, packed binary")
    same_row = (packed.doc_id == spans["_doc"]) & (packed.key == spans["_key"])
    joined = packed.join(spans, same_row, "left").select("doc_id", "packed", F.coalesce("copied", F.lit(False)).alias("copied"), "starts", "ends")
    out = joined.mapInArrow(_finish, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    return out.withColumn("doc_id", F.nullif("doc_id", F.lit(_LAST)))
