"""Substring deduplication by sliding spans of consecutive sentences.

A span is a run of consecutive sentences that one of RULES calls long enough and that has no shorter such run with the same
first or the same last sentence: every run of three sentences whatever their words, every run of two with 20 words, every
run with 50 words. The same passage has the same spans wherever it stands. Spans are hashed (128 bits), grouped over the
whole corpus, and every sentence under a span that is not its first occurrence goes. First is by doc_id, then by position.

Defined results: null text counts as empty and comes back as empty; repeated rows are copies, all but one of them lose
their spans; documents that lose everything stay as rows with empty text; extra columns, whatever their names, are carried
through by strip_repeats; an empty table gives no rows. Texts of any length are read whole.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ROW, fresh, materialize, mix64, slices, with_columns_only, with_rows

#: (sentences, words): a run with so many of both is long enough.
RULES = ((3, 0), (2, 20), (1, 50))
#: Where a sentence ends: after a full stop, question or exclamation mark before white space, or at a line's end; with the white space after it.
_END = re.compile(r"""[.!?]+["'»”)]*(?=\s|$)\s*|\n\s*""")
_B1, _B2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def ends_of(text: str) -> list[int]:
    """Where each sentence of a text ends; the last is the text's end."""
    ends = [m.end() for m in _END.finditer(text)]
    if text and (not ends or ends[-1] < len(text)):
        ends.append(len(text))
    return ends


def sentences(text: str) -> list[str]:
    """The text cut after each sentence or line; joined they are the text again."""
    ends = ends_of(text)
    return [text[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def runs(words: np.ndarray, starts: np.ndarray, ends: np.ndarray, rules: tuple = RULES) -> np.ndarray:
    """Distinct (first, last + 1) of the spans of a row of sentences with so many words each; sentence i is of the text of sentences starts[i] to ends[i] - 1."""
    n = len(words)
    upto = np.concatenate([[0], np.cumsum(words)])
    at = np.arange(n)
    last, first = np.full(n, n + 1), np.full(n, -1)
    for k, w in rules:
        last = np.minimum(last, np.maximum(at + k, np.searchsorted(upto, upto[:-1] + w)))
        first = np.maximum(first, np.minimum(at + 1 - k, np.searchsorted(upto, upto[1:] - w, "right") - 1))
    forward, backward = last <= ends, first >= starts
    key = np.unique(np.concatenate([at[forward] * (n + 1) + last[forward], first[backward] * (n + 1) + at[backward] + 1]))
    return np.stack([key // (n + 1), key % (n + 1)], 1)


def _run_hashes(h: np.ndarray, found: np.ndarray, base: np.uint64) -> np.ndarray:
    """64-bit polynomial hash of each run over sentence hashes h, from sums over prefixes."""
    inverse = np.uint64(pow(int(base), -1, 1 << 64))
    n = len(h)
    up, down = np.full(n + 1, base), np.full(n + 1, inverse)
    up[0] = down[0] = 1
    up, down = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[:-1], dtype=np.uint64)])
    first, last = found[:, 0], found[:, 1]
    return mix64((sums[last] - sums[first]) * down[first] + (last - first).astype(np.uint64))


def span_hashes(texts: list[str], rules: tuple = RULES) -> tuple[np.ndarray, ...]:
    """For the spans of a list of texts: number of the text, first and last + 1 sentence, two 64-bit hashes; white space around sentences does not count."""
    held, index, words, starts, hashes = [], [], [], [], []
    digest = xxhash.xxh3_64_intdigest
    for i, text in enumerate(texts):
        begin, at = len(index), 0
        for k, end in enumerate(ends_of(text)):
            part = text[at:end].split()
            at = end
            if part:
                index.append(k)
                words.append(len(part))
                hashes.append(digest(" ".join(part).encode("utf-8", "surrogatepass")))
        held += [i] * (len(index) - begin)
        starts += [begin] * (len(index) - begin)
    of, places, begins = np.array(held, np.int64), np.array(index, np.int64), np.array(starts, np.int64)
    ends = np.searchsorted(of, of, "right")
    found = runs(np.array(words, np.int64), begins, ends, rules)
    h = np.array(hashes, np.uint64)
    return of[found[:, 0]], places[found[:, 0]], places[found[:, 1] - 1] + 1, _run_hashes(h, found, _B1), _run_hashes(mix64(h ^ _B1), found, _B2)


def _emitter(rules: tuple):
    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            of, first, last, a, b = span_hashes([t.as_py() or "" for t in batch.column("text")], rules)
            rows = batch.column("row").to_numpy(zero_copy_only=False)[of]
            data = [pa.array(rows, pa.int64()), pa.array(first.astype(np.int32)), pa.array(last.astype(np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))]
            yield pa.RecordBatch.from_arrays(data, ["row", "first", "last", "h1", "h2"])

    return emit


def repeated_spans(rows: DataFrame, rules: tuple = RULES) -> DataFrame:
    """row, gone (array of first << 32 | last): the spans of each row to remove. rows: distinct ROW (bigint), text.

    Spans are hashed twice rather than stored. The first pass shuffles 64-bit hashes alone, to learn which occur twice;
    only spans with those go through the exact 128-bit grouping.
    """
    spans = rows.select(F.col(ROW).alias("row"), "text").mapInArrow(_emitter(rules), "row bigint, first int, last int, h1 bigint, h2 bigint")
    twice = materialize(spans.groupBy("h1").agg(F.count("*").alias("n")).where("n > 1").select("h1"), "twice")  # written, so that AQE can split a hot hash in the join
    likely = materialize(spans.join(twice, "h1"), "spans")
    place = F.struct("row", "first")
    origin = likely.groupBy("h1", "h2").agg(F.min(place).alias("origin"), F.count("*").alias("n")).where("n > 1").drop("n")
    origin = materialize(origin, "origins")  # likewise
    later = likely.join(origin, ["h1", "h2"]).where(place != F.col("origin"))
    mark = F.shiftleft(F.col("first").cast("bigint"), 32) + F.col("last")
    return later.groupBy("row").agg(F.collect_list(mark).alias("gone"))


def _left(text: str, gone: np.ndarray | None) -> tuple[str, int, int]:
    """A text without the sentences under the marks, how many it had and how many went."""
    ends = ends_of(text)
    if gone is None or not len(gone):
        return text, len(ends), 0
    edge = np.zeros(len(ends) + 1, np.int64)
    np.add.at(edge, gone >> 32, 1)
    np.add.at(edge, gone & 0xFFFFFFFF, -1)
    keep = (np.cumsum(edge)[:-1] == 0).tolist()
    kept = "".join([text[a:b] for a, b, k in zip([0, *ends], ends, keep, strict=False) if k])
    return kept.rstrip(), len(ends), len(ends) - sum(keep)


def _cut(texts: pa.Array, gone: pa.Array) -> list[tuple[str, int, int]]:
    return [_left(t.as_py() or "", g.values.to_numpy(zero_copy_only=False) if g.is_valid else None) for t, g in zip(texts, gone, strict=True)]


def _with_marks(rows: DataFrame, rules: tuple) -> tuple[DataFrame, str]:
    """rows with an array column of marks, and its name."""
    of, gone = fresh(rows.columns, "of", "gone")
    marks = repeated_spans(rows, rules).withColumnsRenamed({"row": of, "gone": gone})
    return rows.join(marks, F.col(ROW) == F.col(of), "left").drop(of, ROW), gone


def dedup(docs: DataFrame, rules: tuple = RULES) -> DataFrame:
    """doc_id, text (what is left), n_sentences, n_removed: one row per row of docs."""
    joined, gone = _with_marks(with_rows(with_columns_only(docs, "doc_id", "text")), rules)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts, total, removed = zip(*_cut(b.column("text"), b.column(gone)), strict=True) if b.num_rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(texts, pa.string()), pa.array(total, pa.int32()), pa.array(removed, pa.int32())], ["doc_id", "text", "n_sentences", "n_removed"])

    return joined.withColumn("doc_id", F.col("doc_id").cast("bigint")).mapInArrow(cut, "doc_id bigint, text string, n_sentences int, n_removed int")


def strip_repeats(docs: DataFrame, rules: tuple = RULES) -> DataFrame:
    """docs with repeated spans cut out of text and n_chars set anew; every row and every other column stays."""
    joined, gone = _with_marks(with_rows(docs), rules)
    others = [c for c in docs.columns if c != "text"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts = [t for t, _, _ in _cut(b.column("text"), b.column(gone))]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in others], pa.array(texts, pa.string())], [*others, "text"])

    done = joined.mapInArrow(cut, joined.select(*[F.col(f"`{c}`") for c in others], "text").schema)
    if "n_chars" in docs.columns:
        done = done.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return done.select(*[F.col(f"`{c}`") for c in docs.columns])
