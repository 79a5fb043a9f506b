"""Packing of token sequences into few sequences of fixed capacity.

Only the histogram of lengths matters for a plan: `capacity` rows at most, whatever the corpus. On the driver, lengths are
opened from the longest down. Indexes by sum of single lengths, pairs and triples are asked for a combination that fills
the gap exactly, and a combination is consumed as often as its lengths are available at once; where none fills it, the
longest length that fits is added (best fit) until nothing fits. Each step exhausts a length, so the plan stays small.
Lengths only ever become fewer, so an index remembers for each sum how far its combinations are used up and never looks at
these again.

Pieces find their place by their rank among pieces of the same length, counted in two levels (inside a written part, then
over parts), so that a length that a third of the rows share is no bottleneck.

Defined results: null text counts as empty (one piece with the end id); repeated rows are packed like others; an empty
table gives no rows; extra columns, whatever their names, are ignored; longer texts are cut into pieces of `capacity` ids.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import batch_rows, drop_caches, materialize, with_columns_only
from .tokens import cached

CAPACITY, END = 4096, 1
#: Texts handed to a worker at once.
TEXTS = 1000
_PIECE = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, part int, nth bigint"


def _pieces(path: str, capacity: int, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, part = cached(path, True), TaskContext.get().partitionId()
        seen = np.zeros(capacity + 1, np.int64)
        for b in batches:
            rows: list[list] = [[], [], [], [], [], []]
            for doc, ids in zip(b.column("doc_id").to_pylist(), tokenizer.encode(b.column("text")), strict=True):
                ids = np.append(ids, np.uint32(end))
                for piece, start in enumerate(range(0, len(ids), capacity)):
                    own = ids[start : start + capacity]
                    for c, x in zip(rows, (doc, piece, start, len(own), zlib.crc32(own.astype("<u4").tobytes()), int(seen[len(own)])), strict=True):
                        c.append(x)
                    seen[len(own)] += 1
            doc, piece, start, length, crc, nth = rows
            yield pa.RecordBatch.from_arrays(
                [pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array([part] * len(doc), pa.int32()), pa.array(nth, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32", "part", "nth"],
            )

    return run


class Sums:
    """Combinations of available lengths by their sum. have[x]: how many pieces of length x there are; it may only fall."""

    def __init__(self, have: list[int]):
        self.have = have
        #: For each sum, the greatest part that a pair (or triple) of it may still have.
        self.pair_from: dict[int, int] = {}
        self.triple_from: dict[int, int] = {}

    def pair(self, total: int) -> tuple[int, int] | None:
        """Two available lengths, the longer one first and as long as can be."""
        have, a = self.have, self.pair_from.get(total, total - 1)
        while 2 * a >= total:
            if have[a] and have[total - a] > (2 * a == total):
                break
            a -= 1
        self.pair_from[total] = a
        return (a, total - a) if 2 * a >= total else None

    def triple(self, total: int) -> tuple[int, int, int] | None:
        """Three available lengths, one of them as long as can be."""
        have, a = self.have, self.triple_from.get(total, total - 2)
        found = None
        while 3 * a >= total and found is None:
            if have[a]:
                have[a] -= 1
                two = self.pair_below(total - a, a)
                have[a] += 1
                found = two and (a, *two)
            if found is None:
                a -= 1
        self.triple_from[total] = a
        return found

    def pair_below(self, total: int, most: int) -> tuple[int, int] | None:
        """A pair none of which is longer than `most`; looks only where the index says that pairs are left."""
        have = self.have
        for a in range(min(most, self.pair_from.get(total, total - 1)), (total - 1) // 2, -1):
            if have[a] and have[total - a] > (2 * a == total):
                return a, total - a
        return None

    def fill(self, gap: int) -> tuple[int, ...] | None:
        """One, two or three available lengths whose sum is gap."""
        return (gap,) if self.have[gap] else self.pair(gap) or self.triple(gap)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, dict[int, int]]]:
    """[(how many sequences, {length: pieces of it in each})] that hold every piece once."""
    have = [0] * (capacity + 1)
    for length, n in histogram.items():
        have[length] = n
    sums, out, longest = Sums(have), [], capacity
    while True:
        while longest and not have[longest]:
            longest -= 1
        if not longest:
            return out
        parts = {longest: 1}
        have[longest] -= 1
        gap = capacity - longest
        while gap:
            found = sums.fill(gap)
            if found is None:
                fits = next((x for x in range(min(gap, longest), 0, -1) if have[x]), None)
                if fits is None:
                    break
                found = (fits,)
            for x in found:
                parts[x] = parts.get(x, 0) + 1
                have[x] -= 1
                gap -= x
        more = min(have[x] // k for x, k in parts.items())
        for x, k in parts.items():
            have[x] -= more * k
        out.append((1 + more, parts))


def _places(steps: list[tuple[int, dict[int, int]]], capacity: int) -> dict[str, np.ndarray]:
    """For each length, its ranks cut into stretches: where each begins, its sequences, pieces per sequence and offset."""
    rows, base, ranks = [], 0, np.zeros(capacity + 1, np.int64)
    for times, parts in steps:
        offset = 0
        for length, each in parts.items():
            rows.append((length, int(ranks[length]), base, each, offset))
            ranks[length] += times * each
            offset += length * each
        base += times
    table = np.array(sorted(rows), np.int64).reshape(-1, 5)
    return dict(zip(("length", "rank", "base", "each", "offset"), table.T, strict=True))


def _seated(places, capacity: int):
    shift = 62 - capacity.bit_length()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        drop_caches()
        t = places.value
        keys = (t["length"] << shift) + t["rank"]
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            row = np.searchsorted(keys, (length << shift) + rank, "right") - 1
            inside, each = rank - t["rank"][row], t["each"][row]
            seq, offset = t["base"][row] + inside // each, t["offset"][row] + inside % each * length
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")], pa.array(seq), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row per piece. path: a word vocabulary file."""
    d = with_columns_only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("bigint"))
    with batch_rows(docs.sparkSession, TEXTS):
        pieces = materialize(d.mapInArrow(_pieces(path, capacity, end), _PIECE), "pieces")
    held = pieces.groupBy("length", "part").agg(F.count("*").alias("n"))
    before = held.select("length", "part", (F.sum("n").over(W.partitionBy("length").orderBy("part")) - F.col("n")).alias("before"))
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # `capacity` rows at most
    places = docs.sparkSession.sparkContext.broadcast(_places(plan(counts, capacity), capacity))
    ranked = pieces.join(before, ["length", "part"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("nth")).alias("rank"))
    return ranked.mapInArrow(_seated(places, capacity), "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint")
