"""Exact n-gram Jaccard join with vertical partitioning.

N-grams (64-bit hashes of word runs) stand in one global order: by how many documents hold them, rare ones first, then
by hash. Two sets that are similar enough share an n-gram among the first few of both in that order (their prefixes),
so only the prefixes are shuffled to find candidates. The order is cut into fragments; a candidate pair's overlap is
counted fragment by fragment and summed per pair, so no task ever needs a whole set.

Documents with equal sets are one class with one representative. Only connectivity is asked for, so a pair inside one
component needs no test: rounds of single candidates per document (the pivot it shares most prefix n-grams with) link
large groups at linear cost, as long as they find links and many pairs are left; then every pair of representatives in a
common prefix bucket and still in different components is tested, so no link between different sets is lost. Pairs left
then are texts that share rare n-grams without being similar enough; where a corpus has large groups of these (texts put
together from the same few lines), their number grows with the square of such a group.

The document frequencies come from a sketch of 2**SKETCH_BITS counters over all documents, a table of fixed size. They
only order the n-grams: results are exact whatever the sketch says. A corpus beyond 10**11 n-grams wants more bits.

Defined results: null text counts as empty; sets of empty texts are empty and link with nothing; repeated rows are in
one component; of repeated or null doc_ids each row is a document of its own; extra columns, whatever their names, are ignored
by near_groups and kept by keep_one; an empty table gives no rows; texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, ROW, fresh, materialize, maybe_broadcast, mix64, roll, slices, with_columns_only, with_rows
from .components import components

SKETCH_BITS = 22
_RANGES = 16
#: Rounds of single candidates at most, and for how many pairs left per member another one is made.
_PIVOT_ROUNDS, _PAIRS = 4, 8
_HALVES = 1


def shingles(text: str | None, width: int) -> np.ndarray:
    """Distinct hashes (uint64) of the runs of `width` words, letters A-Z lower-cased; of all words if they are fewer."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = np.array([xxhash.xxh3_64_intdigest(w) for w in words], np.uint64)
    return np.unique(roll(h, min(width, len(h))))


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def _profile(width: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["row", "doc_id", "n", "s1", "s2", "part", "counts"]
        mask, counts, any_rows = np.uint64((1 << bits) - 1), np.zeros(1 << bits, np.uint32), False
        salt = np.uint64(0xD6E8FEB86659FD93)
        for b in slices(batches):
            n, s1, s2, held = [], [], [], []
            for t in b.column("text"):
                g = shingles(t.as_py(), width)
                n.append(len(g))
                s1.append(int(mix64(g).sum(dtype=np.uint64).view(np.int64)) if len(g) else 0)
                s2.append(int(mix64(g ^ salt).sum(dtype=np.uint64).view(np.int64)) if len(g) else 0)
                held.append((g & mask).astype(np.int64))
            if held:
                any_rows = True
                at, times = np.unique(np.concatenate(held), return_counts=True)
                counts[at] += times.astype(np.uint32)
            yield pa.RecordBatch.from_arrays([b.column("row"), b.column("doc_id"), pa.array(n, pa.int64()), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.nulls(len(n), pa.int32()), pa.nulls(len(n), pa.binary())], names)
        if any_rows:
            chunks = counts.reshape(_RANGES, -1)
            packed = [pa.compress(c.tobytes(), codec="zstd", asbytes=True) for c in chunks]
            none = pa.nulls(_RANGES, pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, none, none, none, pa.array(range(_RANGES), pa.int32()), pa.array(packed, pa.binary())], names)

    return run


def _add_up(bits: int):
    size = 4 * ((1 << bits) // _RANGES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for b in batches:
            for part, packed in zip(b.column("part").to_pylist(), b.column("counts"), strict=True):
                x = np.frombuffer(pa.decompress(packed.as_buffer(), decompressed_size=size, codec="zstd"), np.uint32)
                total[part] = total.get(part, np.uint64(0)) + x.astype(np.uint64)
        levels = [np.floor(np.log2(total[p] + np.uint64(1)) / 2).astype(np.uint8).tobytes() for p in sorted(total)]
        yield pa.RecordBatch.from_arrays([pa.array(sorted(total), pa.int32()), pa.array(levels, pa.binary())], ["part", "levels"])

    return run


def _ordered(g: np.ndarray, levels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """g in the global order, and the fragment of each: a level and a half of the hash range."""
    level = levels[(g & np.uint64(len(levels) - 1)).astype(np.int64)]
    at = np.lexsort((g, level))
    g, level = g[at], level[at].astype(np.int32)
    return g, level << _HALVES | (g >> np.uint64(64 - _HALVES)).astype(np.int32)


class JaccardJoin:
    """Links of documents whose n-gram sets have `den` * |A and B| >= `num` * |A or B|."""

    def __init__(self, rows: DataFrame, width: int, num: int, den: int = 100, sketch_bits: int = SKETCH_BITS):
        """rows: what with_rows gives of doc_id and text."""
        self.width, self.num, self.den, self.bits = width, num, den, sketch_bits
        self.spark = rows.sparkSession
        d = rows.select(F.col(ROW).alias("row"), F.col("doc_id").cast("bigint").alias("doc_id"), "text")
        self.docs = d.select("row", "text")
        found = materialize(d.select("row", "doc_id", "text").mapInArrow(_profile(width, sketch_bits), "row bigint, doc_id bigint, n bigint, s1 bigint, s2 bigint, part int, counts binary"), "profile")
        self.profile = found.where("counts is null").select("row", "doc_id", "n", "s1", "s2")
        rows = found.where("counts is not null").select("part", "counts").repartition(_RANGES, "part").mapInArrow(_add_up(sketch_bits), "part int, levels binary").collect()  # 2**bits bytes
        levels = np.zeros(1 << sketch_bits, np.uint8)
        for r in rows:
            chunk = (1 << sketch_bits) // _RANGES
            levels[r["part"] * chunk : (r["part"] + 1) * chunk] = np.frombuffer(r["levels"], np.uint8)
        self.levels = self.spark.sparkContext.broadcast(levels)
        self.classes = materialize(self.profile.where("n > 0").groupBy("s1", "s2", "n").agg(F.min("row").alias("rep"), F.count("*").alias("copies")), "classes")

    def _prefixes(self) -> DataFrame:
        """id, n, tokens: the prefix of every representative, in order."""
        width, levels, num, den = self.width, self.levels, self.num, self.den

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in slices(batches):
                n, cut = [], []
                for t in b.column("text"):
                    g = shingles(t.as_py(), width)
                    n.append(len(g))
                    cut.append(_signed(_ordered(g, levels.value)[0][: len(g) + num * len(g) // -den + 1 if len(g) else 0]))
                offsets = np.concatenate([[0], np.cumsum([len(c) for c in cut])]).astype(np.int32)
                tokens = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(cut) if cut else np.empty(0, np.int64)))
                yield pa.RecordBatch.from_arrays([b.column("row"), pa.array(n, pa.int64()), tokens], ["id", "n", "tokens"])

        copies = self.profile.join(self.classes.where("copies > 1").select("s1", "s2", "n", "rep"), ["s1", "s2", "n"]).where("row <> rep").select("row")
        kept = self.docs.join(maybe_broadcast(copies, 16), "row", "left_anti")
        return materialize(kept.mapInArrow(run, "id bigint, n bigint, tokens array<bigint>"), "prefixes")

    def _segments(self, rows: DataFrame, carried: list[str]) -> DataFrame:
        """rows (text and carried bigint columns) -> carried, fragment, grams."""
        width, levels = self.width, self.levels

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in slices(batches):
                at, fragments, offsets, values = [], [], [0], []
                for i, t in enumerate(b.column("text")):
                    g, fragment = _ordered(shingles(t.as_py(), width), levels.value)
                    edges = np.flatnonzero(np.diff(fragment, prepend=-1))
                    at += [i] * len(edges)
                    fragments.append(fragment[edges])
                    offsets += (offsets[-1] + np.append(edges[1:], len(g))).tolist() if len(g) else []
                    values.append(_signed(g))
                lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(values) if values else np.empty(0, np.int64)))
                index = pa.array(at, pa.int64())
                yield pa.RecordBatch.from_arrays([*[b.column(c).take(index) for c in carried], pa.array(np.concatenate(fragments) if fragments else [], pa.int32()), lists], [*carried, "fragment", "grams"])

        return rows.select(*carried, "text").mapInArrow(run, ", ".join(f"{c} bigint" for c in carried) + ", fragment int, grams array<bigint>")

    def _linked(self, pairs: DataFrame) -> DataFrame:
        """Those (u, v) of pairs (a, b, na, nb) that are similar enough: overlaps counted per fragment, then summed."""
        few = pairs.count() * 40 <= BROADCAST_BYTES
        mark = F.broadcast if few else (lambda x: x)
        right = self._segments(self.docs.join(mark(pairs), F.col("row") == F.col("b")), ["a", "b", "na", "nb"])
        left = self._segments(self.docs.join(mark(pairs.select("a").distinct()), F.col("row") == F.col("a")), ["a"])
        met = right.join(left.withColumnRenamed("grams", "others"), ["a", "fragment"])
        part = met.select("a", "b", "na", "nb", F.size(F.array_intersect("grams", "others")).cast("bigint").alias("both"))
        total = part.groupBy("a", "b", "na", "nb").agg(F.sum("both").alias("both"))
        return total.where(self.den * F.col("both") >= self.num * (F.col("na") + F.col("nb") - F.col("both"))).select(F.col("a").alias("u"), F.col("b").alias("v"))

    def _fits(self, x: str, y: str) -> F.Column:
        """Sizes alone allow a link."""
        return self.den * F.least(x, y) >= self.num * F.greatest(x, y)

    def _need(self, na, nb) -> F.Column:
        """Overlap that a link of sets of these sizes needs."""
        return F.ceil(self.num * (F.col(na) + F.col(nb)) / F.lit(self.num + self.den))

    def _likely(self, pairs: DataFrame, prefixes: DataFrame) -> DataFrame:
        """Those pairs (a, b, na, nb) with as many common n-grams in the two prefixes as a link must have.

        All n-grams of the set whose prefix ends first in the order, up to that end, are in both prefixes if they are
        common; of its rest it has one less than the overlap it needs with any partner. Both must add up to the overlap of
        a link.
        """
        pairs = materialize(pairs, "pairs")
        mark = F.broadcast if pairs.count() * 40 <= BROADCAST_BYTES else (lambda x: x)
        one = prefixes.select(F.col("id").alias("a"), F.col("tokens").alias("ta")).join(mark(pairs), "a")
        both = prefixes.select(F.col("id").alias("b"), F.col("tokens").alias("tb")).join(one, "b")
        least = F.ceil(self.num * F.greatest("na", "nb") / F.lit(self.den))
        ok = both.where(F.size(F.array_intersect("ta", "tb")) >= self._need("na", "nb") - least + 1)
        return materialize(ok.select("a", "b", "na", "nb"), "likely")

    def links(self) -> tuple[DataFrame, DataFrame]:
        """Tested links (u, v) between representatives that connect all that are linked, and node, component over them."""
        prefixes = self._prefixes()
        every = prefixes.select("id", "n", F.posexplode("tokens").alias("pos", "token"))
        shared = every.groupBy("token").agg(F.count("*").alias("held")).where("held > 1").select("token")
        members = materialize(every.join(shared, "token").withColumn("comp", F.col("id")), "members")
        edges = self.spark.createDataFrame([], "u bigint, v bigint")
        found = None
        for turn in range(_PIVOT_ROUNDS):
            pick = F.min if turn % 2 == 0 else F.max
            heads = members.groupBy("token").agg(pick(F.struct("comp", "id", "n")).alias("head"))
            met = members.join(heads, "token").where((F.col("comp") != F.col("head.comp")) & self._fits("n", "head.n"))
            votes = met.groupBy(F.col("head.id").alias("a"), F.col("id").alias("b"), F.col("head.n").alias("na"), F.col("n").alias("nb")).agg(F.count("*").alias("common"))
            best = votes.groupBy("b", "nb").agg(F.max(F.struct("common", "a", "na")).alias("best")).select("best.a", "b", "best.na", "nb")
            new = materialize(self._linked(self._likely(best, prefixes)), "links")
            if new.isEmpty():
                break
            edges = edges.union(new)
            found = materialize(components(edges), "components")
            members = self._open(members.drop("comp"), found)
            rows, pairs = members.groupBy("token").agg(F.count("*").alias("n")).agg(F.sum("n"), F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()
            if not rows or pairs <= _PAIRS * rows:
                break
        # Linked sets share an n-gram that comes so early in both that what follows it can still make up the overlap.
        x, y = members.alias("x"), members.alias("y")
        need = self._need("x.n", "y.n")
        early = (F.col("x.pos") <= F.col("x.n") - need) & (F.col("y.pos") <= F.col("y.n") - need)
        near = x.join(y, "token").where((F.col("x.comp") < F.col("y.comp")) & self._fits("x.n", "y.n") & early)
        pairs = near.select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), F.col("x.n").alias("na"), F.col("y.n").alias("nb")).distinct()
        last = materialize(self._linked(self._likely(pairs, prefixes)), "links")
        if not last.isEmpty():
            edges = edges.union(last)
            found = materialize(components(edges), "components")
        return edges, found if found is not None else self.spark.createDataFrame([], "node bigint, component bigint")

    def _open(self, members: DataFrame, found: DataFrame) -> DataFrame:
        """Members of the buckets that still hold two components."""
        placed = members.join(maybe_broadcast(found, 24), F.col("id") == F.col("node"), "left").select("token", "id", "n", "pos", F.coalesce("component", "id").alias("comp"))
        mixed = placed.groupBy("token").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("token")
        return materialize(placed.join(mixed, "token"), "members")

    def result(self) -> DataFrame:
        """row, doc_id, n_shingles, component (a row), component_id (a doc_id): one row per document."""
        _, found = self.links()
        rooted = self.classes.join(found, F.col("rep") == F.col("node"), "left").select("s1", "s2", "n", F.coalesce("component", "rep").alias("component"))
        placed = self.profile.join(rooted, ["s1", "s2", "n"], "left").select("row", "doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "row").alias("component"))
        if self.docs_keep_ids:
            return placed.withColumn("component_id", F.col("component"))
        names = self.profile.select(F.col("row").alias("component"), F.col("doc_id").alias("component_id"))
        return placed.join(names, "component", "left")

    @property
    def docs_keep_ids(self) -> bool:
        return self.profile.where("not (row <=> doc_id)").isEmpty()


def near_groups(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """doc_id, n_shingles, component_id for the links of the given similarity (five words and 0.8 by default)."""
    return JaccardJoin(with_rows(with_columns_only(docs, "doc_id", "text")), width, num, den).result().select("doc_id", "n_shingles", "component_id")


def keep_one(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """docs without all but the first document (least doc_id) of each group of linked ones; all columns stay."""
    rows = with_rows(docs)
    (of,) = fresh(rows.columns, "gone")
    gone = JaccardJoin(rows, width, num, den).result().where("row <> component").select(F.col("row").alias(of))
    return rows.join(maybe_broadcast(gone, 16), F.col(ROW) == F.col(of), "left_anti").drop(ROW)
