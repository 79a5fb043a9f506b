"""Exact top-k inner products over norm-sorted vectors.

Vectors become integers, floor(scale * x). They are written in descending order of length, in blocks, with their
coordinates in the basis of the Gram matrix's eigenvectors (the right singular vectors) at hand, so that the first few
coordinates hold most of every inner product. The longest BEST vectors, one block of fixed size, give each query a first
bound on its k-th score. Blocks of queries then meet blocks of vectors, pair by pair on the executors: pairs whose lengths
cannot reach the bound of any query of the block are never formed; in the others the partial sum over HEAD coordinates
plus the Cauchy-Schwarz bound on what remains prunes vectors, and exact integer products are taken of those left. Bounds
rise as a task goes on, and carry a slack above rounding errors, so no result is lost.

Nothing but that one block, the Gram matrix and counts reaches the driver.

Defined results: vectors that are null, empty or hold a null or a non-finite component take no part, nor do null ids or
vectors with a scaled component of 2**62 or more, whose scores would not fit a long; every row is a candidate and, if its id
asks, a query of its own, even where ids repeat; vectors of unlike lengths are filled up with zeros; extra columns,
whatever their names, are ignored; an empty table gives no rows. Ties go to the smaller vec_id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import batch_rows, materialize, with_columns_only

ROWS, BEST, STEP, HEAD = 4096, 4096, 256, 16


def _whole(vectors: DataFrame, scale: int) -> DataFrame:
    """vec_id, x (array<double> of whole numbers)."""
    v = with_columns_only(vectors, "vec_id", "embedding").where("vec_id is not null and size(embedding) > 0")
    x = F.transform("embedding", lambda c: F.lit(float(scale)) * c.cast("double"))
    ok = F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < 2.0**62))
    v = v.select(F.col("vec_id").cast("bigint").alias("vec_id"), x.alias("x")).where(ok)
    return v.select("vec_id", F.transform("x", lambda c: F.floor(c).cast("double")).alias("x"))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    flat, ends = column.flatten().to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    ends = ends - ends[0]
    if len(column) and (np.diff(ends) == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(column), width))
    for i, (a, b) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
        out[i, : b - a] = flat[a:b]
    return out


def _gram(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((width, width))
        for b in batches:
            m = _matrix(b.column("x"), width)
            total += m.T @ m
        cell = np.arange(width * width)
        yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(total.ravel())], ["cell", "part"])

    return run


def rotation(x: DataFrame, width: int) -> np.ndarray:
    """Orthonormal basis, directions of most weight first; from width**2 sums over all vectors."""
    cells = x.select("x").mapInArrow(_gram(width), "cell bigint, part double").groupBy("cell").agg(F.sum("part").alias("v")).collect()
    gram = np.zeros(width * width)
    for r in cells:
        gram[r["cell"]] = r["v"]
    gram = gram.reshape(width, width)
    if not np.isfinite(gram).all():
        return np.eye(width)
    return np.linalg.eigh((gram + gram.T) / 2)[1][:, ::-1]


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact inner products of whole-number rows, pair by pair."""
    if np.abs(a).max(initial=0) * np.abs(b).max(initial=0) * a.shape[1] < 2.0**52:
        return np.einsum("ij,ij->i", a, b).astype(np.int64)
    return np.einsum("ij,ij->i", a.astype(np.int64), b.astype(np.int64))


class _Best:
    """The k best (score, vec_id) of each query so far."""

    def __init__(self, queries: int, k: int):
        self.k, self.q, self.score, self.vec = k, np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
        self.least = np.full(queries, np.iinfo(np.int64).min, np.int64)

    def add(self, q: np.ndarray, score: np.ndarray, vec: np.ndarray) -> None:
        q, score, vec = np.concatenate([self.q, q]), np.concatenate([self.score, score]), np.concatenate([self.vec, vec])
        at = np.lexsort((vec, -score, q))
        q, score, vec = q[at], score[at], vec[at]
        place = np.arange(len(q)) - np.searchsorted(q, q)
        keep = place < self.k
        self.q, self.score, self.vec = q[keep], score[keep], vec[keep]
        last = place[keep] == self.k - 1
        self.least[self.q[last]] = np.maximum(self.least[self.q[last]], self.score[last])


class _Asked:
    """A block of queries with their best vectors so far."""

    def __init__(self, rows: np.ndarray, m: np.ndarray, basis: np.ndarray, k: int, least: np.ndarray | None = None):
        self.rows, self.m, self.turned = rows, m, m @ basis
        self.norm, self.rest = np.sqrt((m * m).sum(1)), np.sqrt((self.turned[:, _head(m) :] ** 2).sum(1))
        self.best = _Best(len(rows), k)
        if least is not None:
            self.best.least = np.maximum(self.best.least, least)

    def meet(self, rows: np.ndarray, ids: np.ndarray, m: np.ndarray, basis: np.ndarray) -> None:
        """Vectors m, in descending order of length, against all queries."""
        for a in range(0, len(ids), STEP):
            self._meet(rows[a : a + STEP], ids[a : a + STEP], m[a : a + STEP], basis)

    def _meet(self, rows: np.ndarray, ids: np.ndarray, m: np.ndarray, basis: np.ndarray) -> None:
        best, head = self.best, _head(m)
        norm = np.sqrt((m * m).sum(1))
        bound = best.least.astype(float)
        slack = 1e-9 * (1 + norm.max(initial=0) * self.norm)
        open_q = np.flatnonzero(norm.max(initial=0) * self.norm + slack >= bound)
        if not len(open_q):
            return
        turned = m @ basis
        rest = np.sqrt((turned[:, head:] ** 2).sum(1))
        most = self.turned[open_q, :head] @ turned[:, :head].T + np.outer(self.rest[open_q], rest)
        q, v = np.nonzero(most + slack[open_q, None] >= bound[open_q, None])
        q = open_q[q]
        other = self.rows[q] != rows[v]
        q, v = q[other], v[other]
        for a in range(0, len(q), 200_000):
            qq, vv = q[a : a + 200_000], v[a : a + 200_000]
            score = _products(self.m[qq], m[vv])
            ok = score >= best.least[qq]
            best.add(qq[ok], score[ok], ids[vv[ok]])

    def needed(self) -> float:
        """The least length that a vector must have to be among the best of any query."""
        bound = self.best.least.astype(float)
        safe = np.where(self.norm > 0, bound / np.maximum(self.norm, 1e-300), np.where(bound > 0, np.inf, -np.inf))
        least = float(safe.min(initial=np.inf))
        return least * (1 - 1e-9) if least > 0 else -1.0


def _head(m: np.ndarray) -> int:
    return min(HEAD, m.shape[1])


_BLOCK = "block bigint, longest double, rows binary, ids binary, x binary"
_QUERY = "of bigint, needed double, asked binary, names binary, least binary, y binary"


def _parts(b: pa.RecordBatch, width: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    rows, ids, m = b.column("row").to_numpy(), b.column("vec_id").to_numpy(), _matrix(b.column("x"), width)
    for a in range(0, len(ids), ROWS):
        yield rows[a : a + ROWS], ids[a : a + ROWS], m[a : a + ROWS]


def _packed(width: int):
    """Rows (row, vec_id, x) in descending order of length -> blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rows, ids, m in _parts(b, width):
                longest = float(np.sqrt((m * m).sum(1)).max())
                yield pa.RecordBatch.from_pylist([{"block": int(rows[0]), "longest": longest, "rows": rows.tobytes(), "ids": ids.tobytes(), "x": m.tobytes()}], _SCHEMAS["block"])

    return run


def _asking(shared, width: int, k: int):
    """Rows (row, vec_id, x) -> blocks of queries with their first bounds, from the longest vectors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        basis, rows, ids, m = shared.value
        for b in batches:
            for own, names, y in _parts(b, width):
                asked = _Asked(own, y, basis, k)
                asked.meet(rows, ids, m, basis)
                yield pa.RecordBatch.from_pylist([{"of": int(own[0]), "needed": asked.needed(), "asked": own.tobytes(), "names": names.tobytes(), "least": asked.best.least.tobytes(), "y": y.tobytes()}], _SCHEMAS["query"])

    return run


def _search(shared, width: int, k: int):
    """Pairs of blocks -> the best of each query among the vectors that this task met."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        basis = shared.value[0]
        held: dict[int, tuple[_Asked, np.ndarray]] = {}
        for b in batches:
            for i in range(b.num_rows):
                raw = lambda c: b.column(c)[i].as_buffer()  # noqa: E731, B023
                of = b.column("of")[i].as_py()
                if of not in held:
                    asked = np.frombuffer(raw("asked"), np.int64).copy()
                    own = _Asked(asked, np.frombuffer(raw("y")).reshape(-1, width).copy(), basis, k, np.frombuffer(raw("least"), np.int64))
                    held[of] = own, np.frombuffer(raw("names"), np.int64).copy()
                held[of][0].meet(np.frombuffer(raw("rows"), np.int64), np.frombuffer(raw("ids"), np.int64), np.frombuffer(raw("x")).reshape(-1, width), basis)
        for own, names in held.values():
            q = own.best.q
            yield pa.RecordBatch.from_arrays([pa.array(own.rows[q]), pa.array(names[q]), pa.array(own.best.vec), pa.array(own.best.score)], ["row", "query_id", "vec_id", "score"])

    return run


_SCHEMAS = {
    "block": pa.schema([("block", pa.int64()), ("longest", pa.float64()), ("rows", pa.binary()), ("ids", pa.binary()), ("x", pa.binary())]),
    "query": pa.schema([("of", pa.int64()), ("needed", pa.float64()), ("asked", pa.binary()), ("names", pa.binary()), ("least", pa.binary()), ("y", pa.binary())]),
}


def search(vectors: DataFrame, k: int = 5, every: int = 50, scale: int = 256) -> DataFrame:
    """query_id, rank, vec_id, score: the k best other vectors of each vector whose id is divisible by `every`."""
    spark = vectors.sparkSession
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, c: a + c * c))
    x = _whole(vectors, scale).withColumn("norm", norm)
    sort = [F.desc("norm"), F.col("vec_id")]
    x = materialize(x.repartitionByRange(*sort).sortWithinPartitions(*sort).withColumn("row", F.monotonically_increasing_id()), "by-length")
    width = x.agg(F.max(F.size("x"))).first()[0]
    if width is None:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")
    first = x.orderBy(*sort, "row").limit(BEST).select("row", "vec_id", "x").collect()  # BEST rows
    best = np.array([r["row"] for r in first], np.int64), np.array([r["vec_id"] for r in first], np.int64), _rows([r["x"] for r in first], width)
    shared = spark.sparkContext.broadcast((rotation(x, width), *best))
    blocks = materialize(x.select("row", "vec_id", "x").mapInArrow(_packed(width), _BLOCK), "blocks")
    asked = x.where(F.col("vec_id") % every == 0).select("norm", "row", "vec_id", "x").repartitionByRange(*sort).sortWithinPartitions(*sort, "row")
    asked = materialize(asked.drop("norm").mapInArrow(_asking(shared, width, k), _QUERY), "queries")
    pairs = blocks.join(asked, F.col("longest") >= F.col("needed")).drop("block", "longest", "needed")
    with batch_rows(spark, 8):  # a row is two blocks
        found = materialize(pairs.mapInArrow(_search(shared, width, k), "row bigint, query_id bigint, vec_id bigint, score bigint"), "found")
    by = W.partitionBy("row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _rows(xs: list, width: int) -> np.ndarray:
    out = np.zeros((len(xs), width))
    for i, x in enumerate(xs):
        out[i, : len(x)] = x
    return out
