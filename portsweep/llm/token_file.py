"""Token-id files: an adaptive context-mixing range coder over independent, checksummed blocks.

A block holds up to BLOCK ids and starts from empty models, so that it is read without any other. Its bytes are a header
(MAGIC, or MAGIC_WIDE if an id needs more than 16 bits; number of ids, CRC-32 of the ids as little-endian unsigned 32-bit integers; all little-endian) and the coder's
16-bit words. For each id the order-2 and the order-1 context predict one id each, and order 0 keeps counts of recent
ids in hashed slots. What happens (hit by order 2, by order 1, by an order-0 slot, or none) is coded with a mix of three
adaptive distributions, one chosen by each order's confidence, weighted by how well each has done; then the slot by its
counts, or the id plainly.

The coder has two forms with the same bytes. Files are written and read by the one in TokenBlocks.java, block by block in the
executors' JVM: the driver compiles it with the compiler that Spark brings along and adds it to the session as a jar. Python
workers only make the ids. encode_blocks() and decode_blocks() are the form without Spark: all blocks of a batch are coded
in step, one id of each at a time, as array operations.

Files are Parquet rows in ascending doc_id order, each of whole documents: part and before (ids of the part before this
row), the documents' ids and lengths, and their blocks.

Defined results: null text counts as empty (the end id alone); rows that repeat a doc_id follow each other in an order
fixed by their text; extra columns are ignored; texts are coded whole. The ids of one document must fit in 2 GB.
"""

from __future__ import annotations

import os
import struct
import tempfile
import uuid
import zipfile
import zlib
from collections.abc import Iterator
from functools import cache
from importlib.resources import files as package_files

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import maybe_broadcast, scratch_dir, with_columns_only
from .tokens import cached

BLOCK, LANES, ROW_IDS = 2048, 2048, 32_768
#: Ids that a Python worker hands over at once, in rows of whole documents.
HANDED_IDS = 1 << 20
MAGIC, MAGIC_WIDE = b"TIB3", b"TIB4"
_HEADER = struct.Struct("<4sII")
_CONTEXTS, _SLOTS, _BITS = 1024, 1024, 3
_TRUST = 1 << _BITS
_FULL, _LOW, _ONE = 1 << 48, 1 << 32, 1 << 16
#: Parts of _ONE that every event has at least, and those dealt by the mix.
_LEAST = 16
_SPREAD = np.float32(_ONE - 4 * _LEAST)
#: How fast events are learned; every so many ids the slots' sums, the weights and the events are renewed.
_RATE, _FREEZE, _WEIGH, _COUNT = 0.0625, 64, 4, 2
#: Session functions of the coder.
_ENCODE, _DOCUMENTS, _DOCUMENTS_IDS = "portsweep_encode_blocks", "portsweep_block_documents", "portsweep_block_documents_ids"
_DOCUMENT = "doc_id: bigint, start: bigint, n_tokens: bigint, ids_crc32: bigint"
_FILE = "part int, before bigint, doc_ids array<bigint>, lengths array<bigint>, blocks array<binary>"


class BlockError(ValueError):
    """A block's header or checksum is wrong."""


class _Lanes:
    """Models of many blocks in step; lane i is a block, the first `n` lanes are still running.

    The four events of an order's state are one row, kept as a single 16-byte element so that rows move as one.
    """

    def __init__(self, lanes: int, wide: bool):
        self.lane = np.arange(lanes)
        self.wide = wide
        ids = np.int64 if wide else np.int32
        self.guess = [np.full(lanes * _CONTEXTS, -_TRUST, ids) for _ in range(2)]  # id * _TRUST + trust
        row = np.array([0.25, 0.25, 0.25, 0.25], np.float32).view(np.complex128)
        self.events = [np.repeat(row, lanes * _TRUST), np.repeat(row, lanes * _TRUST), np.repeat(row, lanes)]
        self.weights = [np.full((lanes, 4), 1 / 3, np.float32) for _ in range(3)]
        self.slot_id, self.slot_n = np.full(lanes * _SLOTS, -1, ids), np.ones(lanes * _SLOTS, np.int32)
        self.upto = np.zeros((lanes, _SLOTS + 1), np.int32)
        self.p1, self.p2 = np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
        self.bounds = np.zeros((5, lanes), np.int64)
        self.bounds[4] = _ONE
        self.lanes, self.clock = lanes, 0

    def predict(self, n: int) -> None:
        """What the three orders expect next in the first n lanes, and the bounds of the four events in _ONE parts."""
        if self.clock % _FREEZE == 0:
            np.cumsum(self.slot_n.reshape(self.lanes, _SLOTS)[:n], axis=1, out=self.upto[:n, 1:])
        self.clock += 1
        lane, p1, p2 = self.lane[:n], self.p1[:n], self.p2[:n]
        h = p1 * 40503
        at1 = lane * _CONTEXTS + ((h + (p1 >> 7)) & (_CONTEXTS - 1))
        at2 = lane * _CONTEXTS + (((p1 * 2654435761 + p2 * 40503) >> 9) & (_CONTEXTS - 1))
        self.held = held = self.guess[0].take(at2), self.guess[1].take(at1)
        self.at, self.told, self.trust = (at2, at1), (held[0] >> _BITS, held[1] >> _BITS), (held[0] & (_TRUST - 1), held[1] & (_TRUST - 1))
        self.rows = lane * _TRUST + self.trust[0], lane * _TRUST + self.trust[1], lane
        self.each = [self.events[0].take(self.rows[0]).view(np.float32).reshape(n, 4), self.events[1].take(self.rows[1]).view(np.float32).reshape(n, 4), self.events[2][:n].view(np.float32).reshape(n, 4)]
        mixed = self.weights[0][:n] * self.each[0]
        mixed += self.weights[1][:n] * self.each[1]
        mixed += self.weights[2][:n] * self.each[2]
        self.mixed = mixed
        b = mixed[:, 0] * _SPREAD
        self.bounds[1, :n] = b
        b = b + mixed[:, 1] * _SPREAD
        self.bounds[2, :n] = b
        b = b + mixed[:, 2] * _SPREAD
        self.bounds[3, :n] = b
        self.bounds[1, :n] += _LEAST
        self.bounds[2, :n] += 2 * _LEAST
        self.bounds[3, :n] += 3 * _LEAST

    def learn(self, n: int, event: np.ndarray, x: np.ndarray) -> None:
        lane = self.lane[:n]
        cell = lane * 4 + event
        if self.clock % _WEIGH == 0:
            all_in = self.mixed.ravel().take(cell)
            new = [w[:n, 0] * (e.ravel().take(cell) / all_in * np.float32(0.85)) + np.float32(0.05) for w, e in zip(self.weights, self.each, strict=True)]
            total = new[0] + new[1] + new[2]
            for w, x_new in zip(self.weights, new, strict=True):
                w[:n] = (x_new / total)[:, None]
        if self.clock % _COUNT == 0:
            for k in range(3):
                row = self.each[k] * np.float32(1 - _RATE)
                flat = row.ravel()
                flat[cell] += np.float32(_RATE)
                if k < 2:
                    self.events[k][self.rows[k]] = flat.view(np.complex128)
                else:
                    self.events[k][:n] = flat.view(np.complex128)
        fresh = x * _TRUST + 1
        for k in range(2):
            held, trust = self.held[k], self.trust[k]
            missed = np.where(trust > 1, held - ((trust + 1) >> 1), fresh)
            self.guess[k][self.at[k]] = np.where(self.told[k] == x, held + (trust < _TRUST - 1), missed)
        flat = lane * _SLOTS + slot_of(x)
        known = self.slot_id.take(flat) == x
        self.slot_id[flat] = x
        self.slot_n[flat] = self.slot_n.take(flat) * known + 12 * (1 + known)
        self.p2[:n] = self.p1[:n]
        self.p1[:n] = x


def slot_of(x: np.ndarray) -> np.ndarray:
    return ((x * 2654435761) >> 11) & (_SLOTS - 1)


def _in_order(counts: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Lanes by falling length, and how many run at each step."""
    n = np.array(counts, np.int64)
    order = np.argsort(-n, kind="stable")
    running = len(n) - np.searchsorted(np.sort(n), np.arange(n.max(initial=0)), "right")
    return order, running


def _by_width(blocks: list, wide: list[bool], run) -> list:
    """run(blocks, wide) over the blocks of each width, results in the order of blocks."""
    done: list = [None] * len(blocks)
    for w in (False, True):
        mine = [i for i, x in enumerate(wide) if x is w]
        for at in range(0, len(mine), LANES):
            some = mine[at : at + LANES]
            for i, out in zip(some, run([blocks[i] for i in some], w), strict=True):
                done[i] = out
    return done


def encode_blocks(blocks: list[np.ndarray]) -> list[bytes]:
    """The bytes of each block of ids (any unsigned 32-bit integers)."""
    return _by_width(blocks, [bool(len(b)) and int(b.max()) >= _ONE for b in blocks], _encode)


def _encode(blocks: list[np.ndarray], wide: bool) -> list[bytes]:
    """Range coding: a lane's interval is [low, low + size), size at least 2**32 before each id. Words of 16 bits leave from
    the top of low with a possible carry as a 17th bit, which is added to the words before at the end."""
    order, running = _in_order([len(b) for b in blocks])
    ids = np.zeros((len(running), len(blocks)), np.int64)
    for lane, i in enumerate(order):
        ids[: len(blocks[i]), lane] = blocks[i]
    m = _Lanes(len(blocks), wide)
    width = (4 if wide else 2) * len(running) + 4
    out, used = np.zeros(len(blocks) * width, np.uint32), np.arange(len(blocks)) * width
    low, size = np.zeros(len(blocks), np.int64), np.full(len(blocks), _FULL)
    ends = m.bounds.ravel()

    def shift(n: int) -> None:
        at = np.flatnonzero(size[:n] < _LOW)
        while len(at):
            x = low.take(at)
            out[used.take(at)] = x >> 32
            used[at] += 1
            low[at] = (x & (_LOW - 1)) << 16
            more = size.take(at) << 16
            size[at] = more
            at = at[more < _LOW]

    for t, n in enumerate(running.tolist()):
        x = ids[t, :n]
        m.predict(n)
        lane = m.lane[:n]
        slot = slot_of(x)
        event = np.where(m.told[0] == x, 0, np.where(m.told[1] == x, 1, 3 - (m.slot_id.take(lane * _SLOTS + slot) == x)))
        cell = event * m.lanes + lane
        start = ends.take(cell)
        part = size[:n] >> 16
        low[:n] += part * start
        size[:n] = part * (ends.take(cell + m.lanes) - start)
        more = np.flatnonzero(event > 1)
        if len(more):
            kept, own, mine = event.take(more) == 2, x.take(more), slot.take(more)
            row = more * (_SLOTS + 1)
            flat = m.upto.ravel()
            first = np.where(kept, flat.take(row + mine), own & 0xFFFF)
            share = np.where(kept, flat.take(row + mine + 1) - first, 1)
            part = size.take(more) // np.where(kept, flat.take(row + _SLOTS), _ONE)
            low[more] += part * first
            size[more] = part * share
            if wide:  # upper halves of ids coded plainly
                shift(n)
                at, high = more[~kept], own[~kept] >> 16
                part = size.take(at) >> 16
                low[at] += part * high
                size[at] = part
        shift(n)
        m.learn(n, event, x)
    for _ in range(3):
        out[used] = low >> 32
        used += 1
        low = (low & (_LOW - 1)) << 16
    done: list[bytes] = [b""] * len(blocks)
    words = out.reshape(len(blocks), width)
    for at in range(width - 1, 0, -1):
        words[:, at - 1] += words[:, at] >> 16
    words &= 0xFFFF
    for lane, i in enumerate(order):
        raw = np.ascontiguousarray(blocks[i], "<u4").tobytes()
        done[i] = _HEADER.pack(MAGIC_WIDE if wide else MAGIC, len(blocks[i]), zlib.crc32(raw)) + words[lane, : used[lane] - lane * width].astype("<u2").tobytes()
    return done


def decode_blocks(blocks: list[bytes]) -> list[np.ndarray]:
    """The ids (uint32) of each block; BlockError if one is damaged."""
    for b in blocks:
        if len(b) < _HEADER.size or b[:4] not in (MAGIC, MAGIC_WIDE):
            raise BlockError("not a token block")
    return _by_width(blocks, [b[:4] == MAGIC_WIDE for b in blocks], _decode)


def _decode(blocks: list[bytes], wide: bool) -> list[np.ndarray]:
    heads = [_HEADER.unpack_from(b)[1:] for b in blocks]
    order, running = _in_order([h[0] for h in heads])
    width = (max(len(b) for b in blocks) - _HEADER.size) // 2 + 8
    words = np.zeros((len(blocks), width), np.int64)
    for lane, i in enumerate(order):
        w = np.frombuffer(blocks[i], "<u2", offset=_HEADER.size, count=(len(blocks[i]) - _HEADER.size) // 2)
        words[lane, : len(w)] = w
    m = _Lanes(len(blocks), wide)
    code, size = words[:, 0] << 32 | words[:, 1] << 16 | words[:, 2], np.full(len(blocks), _FULL)
    used, last = m.lane * width + 3, m.lane * width + width - 1
    words = words.ravel()
    ids = np.zeros((len(running), len(blocks)), np.int64)
    ends = m.bounds.ravel()

    def shift(n: int) -> None:
        at = np.flatnonzero(size[:n] < _LOW)
        while len(at):
            place = used.take(at)
            code[at] = code.take(at) << 16 | words.take(np.minimum(place, last.take(at)))
            used[at] = place + 1
            more = size.take(at) << 16
            size[at] = more
            at = at[more < _LOW]

    for t, n in enumerate(running.tolist()):
        m.predict(n)
        lane = m.lane[:n]
        part = size[:n] >> 16
        v = code[:n] // part
        event = (v >= m.bounds[1, :n]).astype(np.int64) + (v >= m.bounds[2, :n]) + (v >= m.bounds[3, :n])
        cell = event * m.lanes + lane
        start = ends.take(cell)
        code[:n] -= part * start
        size[:n] = part * (ends.take(cell + m.lanes) - start)
        x = np.where(event == 0, m.told[0], m.told[1]).astype(np.int64)
        more = np.flatnonzero(event > 1)
        if len(more):
            kept = event.take(more) == 2
            row = more * (_SLOTS + 1)
            flat = m.upto.ravel()
            part = size.take(more) // np.where(kept, flat.take(row + _SLOTS), _ONE)
            v = np.minimum(code.take(more) // part, np.where(kept, flat.take(row + _SLOTS), _ONE) - 1)
            slot = np.zeros(len(more), np.int64)
            step = _SLOTS // 2
            while step:  # the last slot that begins at v or before
                slot += step * (flat.take(row + slot + step) <= v)
                step //= 2
            first = np.where(kept, flat.take(row + slot), v)
            share = np.where(kept, flat.take(row + slot + 1) - first, 1)
            own = np.where(kept, m.slot_id.take(more * _SLOTS + slot), v)
            code[more] -= part * first
            size[more] = part * share
            if wide:
                shift(n)
                at = more[~kept]
                part = size.take(at) >> 16
                high = np.minimum(code.take(at) // part, _ONE - 1)
                code[at] -= part * high
                size[at] = part
                own[~kept] |= high << 16
            x[more] = own
        shift(n)
        ids[t, :n] = x
        m.learn(n, event, x)
    done: list[np.ndarray] = [np.empty(0, np.uint32)] * len(blocks)
    for lane, i in enumerate(order):
        own = ids[: heads[i][0], lane].astype(np.uint32)
        if zlib.crc32(own.astype("<u4").tobytes()) != heads[i][1]:
            raise BlockError("checksum differs")
        done[i] = own
    return done


@cache
def _jar(jvm) -> str:
    """A jar of the classes of TokenBlocks.java, compiled once."""
    compiler = jvm.org.codehaus.janino.SimpleCompiler()
    compiler.setParentClassLoader(jvm.java.lang.Thread.currentThread().getContextClassLoader())
    compiler.cook(package_files(__package__).joinpath("TokenBlocks.java").read_text("utf-8"))
    path = f"{os.path.realpath(tempfile.mkdtemp(prefix='portsweep-'))}/token-blocks-{uuid.uuid4().hex}.jar"
    with zipfile.ZipFile(path, "w") as jar:
        for name, code in compiler.getBytecodes().items():
            jar.writestr(name.replace(".", "/") + ".class", bytes(code))
    return path


def _register(spark: SparkSession) -> None:
    """Gives the session, and its executors by a jar, the coder's functions."""
    if spark.catalog.functionExists(_DOCUMENTS_IDS):
        return
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    path = _jar(jvm)
    spark.sql(f"ADD JAR '{path}'")
    urls = gateway.new_array(jvm.java.net.URL, 1)
    urls[0] = jvm.java.io.File(path).toURI().toURL()
    loader = jvm.java.net.URLClassLoader(urls, jvm.java.lang.Thread.currentThread().getContextClassLoader())

    def add(name: str, kind: str, given: list, returns: str) -> None:
        values = gateway.new_array(jvm.java.lang.Object, len(given))
        for i, x in enumerate(given):
            values[i] = x
        made = loader.loadClass(f"portsweep.TokenBlocks${kind}").getConstructors()[0].newInstance(values)
        spark._jsparkSession.udf().register(name, made, jvm.org.apache.spark.sql.types.DataType.fromDDL(returns))

    add(_ENCODE, "Encode", [], "array<binary>")
    add(_DOCUMENTS, "Documents", [False], f"array<struct<{_DOCUMENT}>>")
    add(_DOCUMENTS_IDS, "Documents", [True], f"array<struct<{_DOCUMENT}, ids: array<bigint>>>")


def _tokenized(path: str, end: int):
    """Rows of a file whose blocks are still ids, as little-endian unsigned 32-bit integers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, part, before = cached(path, False), TaskContext.get().partitionId(), 0
        rows: list[tuple[list, list[np.ndarray]]] = [([], [])]
        size = held = 0
        last = np.array([end], np.uint32)

        def emit() -> pa.RecordBatch:
            nonlocal before, rows, held
            rows = [r for r in rows if r[0]]
            starts, lengths, blocks = [], [], []
            for _, own in rows:
                whole = np.concatenate([x for ids in own for x in (ids, last)]).astype("<u4", copy=False)
                starts.append(before)
                before += len(whole)
                lengths.append([len(ids) + 1 for ids in own])
                blocks.append([whole[a : a + BLOCK].tobytes() for a in range(0, len(whole), BLOCK)])
            data = [[part] * len(rows), starts, [r[0] for r in rows], lengths, blocks]
            types = [pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.binary())]
            rows, held = [([], [])], 0
            return pa.RecordBatch.from_arrays([pa.array(d, t) for d, t in zip(data, types, strict=True)], ["part", "before", "doc_ids", "lengths", "blocks"])

        for b in batches:
            for doc, ids in zip(b.column("doc_id").to_pylist(), tokenizer.encode(b.column("text")), strict=True):
                rows[-1][0].append(doc)
                rows[-1][1].append(ids)
                size += len(ids) + 1
                if size >= ROW_IDS:
                    held += size
                    rows.append(([], []))
                    size = 0
                    if held >= HANDED_IDS:
                        yield emit()
        if rows[0][0]:
            yield emit()

    return run


def write(docs: DataFrame, path: str, out: str, end: int = 0) -> None:
    """Encode docs (doc_id, text) with the vocabulary file at `path`, `end` after each, into token files in folder `out`."""
    d = with_columns_only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("bigint"))
    d = d.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    _register(docs.sparkSession)
    rows = d.mapInArrow(_tokenized(path, end), _FILE)
    rows.withColumn("blocks", F.call_function(_ENCODE, "blocks")).write.parquet(out)


def read(spark: SparkSession, out: str, keep_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids): one row per document of the token files in folder `out`."""
    files = spark.read.schema(_FILE).parquet(out)
    _register(spark)
    own = F.inline(F.call_function(_DOCUMENTS_IDS if keep_ids else _DOCUMENTS, "doc_ids", "lengths", "blocks"))
    docs = files.select("part", "before", own).withColumn("start", F.col("before") + F.col("start"))
    ends = files.select("part", (F.col("before") + F.aggregate("lengths", F.lit(0).cast("bigint"), lambda a, n: a + n)).alias("upto"))
    totals = ends.groupBy("part").agg(F.max("upto").alias("n"))  # a row per file
    first = totals.select(F.col("part").alias("of"), (F.sum("n").over(W.orderBy("part")) - F.col("n")).alias("first"))
    placed = docs.join(maybe_broadcast(first, 24), F.col("part") == F.col("of"))
    return placed.select("doc_id", (F.col("start") + F.col("first")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * keep_ids)


def round_trip(docs: DataFrame, path: str, end: int = 0) -> DataFrame:
    """What read() gives of the files that write() makes, in the shared folder."""
    out = f"{scratch_dir(docs.sparkSession)}/token-files-{uuid.uuid4().hex}"
    write(docs, path, out, end)
    return read(docs.sparkSession, out)
