"""Quality rules as weak supervision: rules vote or abstain, EM learns how far to trust each of them.

Every rule looks at counts of one document and votes good (1), bad (-1) or abstains (0). Over the corpus only the
number of documents per vote pattern is needed: at most 3**RULES rows, whatever the corpus size. Expectation-maximisation
over those patterns estimates each rule's accuracy and the share of good documents; the posterior of a document's
pattern decides, in place of "all rules must pass".

Defined results: null text counts as empty, an empty text fails the base rule, repeated rows are judged alike, extra
columns, whatever their names, are ignored by judge and kept by keep_good, an empty table gives no rows. Texts of any length
are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh, materialize, slices, with_columns_only

SYMBOLS = "#*$%&|<>"
WINDOW = 8
_SPACE = str.maketrans("", "", " \t\n\x0b\x0c\r")
_NO_SYMBOLS = str.maketrans("", "", SYMBOLS)
_LEFT = str.maketrans("", "", " \t\n\x0b\x0c\r0123456789.,;:!?()[]{}\"'-_/\\+=~^`@" + SYMBOLS)

#: Where EM starts from, as probabilities of a bad vote, none, and a good vote; they also weigh as 20 documents.
START_BAD, START_GOOD = np.array([0.4, 0.2, 0.4]), np.array([0.02, 0.18, 0.8])

RULES = ("length", "word_size", "symbols", "repeated_lines", "repeated_words", "letters", "line_ends")
FEATURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_letters", "n_ended")
SCHEMA = "doc_id bigint, " + ", ".join(f"{c} bigint" for c in FEATURES)


def repeated_positions(words: list) -> int:
    """Words in windows of WINDOW words that occur twice or more; exact, by doubling ranks of runs 1, 2, 4, 8."""
    n = len(words)
    if n <= WINDOW:
        return 0
    seen: dict = {}
    ids = np.array([seen.setdefault(w, len(seen)) for w in words], np.int64)
    if len(seen) == n:
        return 0
    width = 1
    while width < WINDOW:
        pairs = ids[: len(ids) - width] * np.int64(n + 1) + ids[width:]
        _, ids = np.unique(pairs, return_inverse=True)
        width *= 2
        if len(ids) and ids.max() + 1 == len(ids):
            return 0
    often = np.bincount(ids)[ids] > 1
    edge = np.zeros(n + 1, np.int64)
    at = np.flatnonzero(often)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + WINDOW, -1)
    return int((np.cumsum(edge[:n]) > 0).sum())


def measure(text: str | None) -> tuple[int, ...]:
    """FEATURES of one text."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    bare = text.translate(_SPACE)
    earlier, dup, lines, ended = set(), 0, 0, 0
    for line in text.split("\n"):
        tail = line.rstrip(" \t\n\x0b\x0c\r")
        if tail.strip(" \t\n\x0b\x0c\r"):
            lines += 1
            ended += tail[-1] in ".!?\"'»”)"
            dup += line in earlier
            earlier.add(line)
    return (len(words), len(bare), len(bare) - len(bare.translate(_NO_SYMBOLS)), dup, repeated_positions(words), lines, len(text.translate(_LEFT)), ended)


def _measure_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", *FEATURES]
    for b in slices(batches):
        rows = [measure(t.as_py()) for t in b.column("text")]
        cols = zip(*rows, strict=True) if rows else [[] for _ in FEATURES]
        yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), *[pa.array(c, pa.int64()) for c in cols]], names)


def features(docs: DataFrame) -> DataFrame:
    """One row of FEATURES per document; one pass over the text, no shuffle."""
    d = with_columns_only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("bigint"))
    return d.mapInArrow(_measure_batches, SCHEMA)


def base_failed() -> F.Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def votes() -> dict[str, F.Column]:
    """A column of 1 (good), -1 (bad) or 0 (abstains) for each of RULES; ratios are compared in integers."""
    c = F.col

    def vote(bad: F.Column, good: F.Column) -> F.Column:
        return F.when(bad, -1).when(good, 1).otherwise(0)

    w = c("n_words")
    return {
        "length": vote(w < 20, w >= 50),
        "word_size": vote((c("word_chars") < 2 * w) | (c("word_chars") > 15 * w), c("word_chars").between(3 * w, 10 * w)),
        "symbols": vote(10 * c("n_symbols") > w, 100 * c("n_symbols") <= w),
        "repeated_lines": vote(10 * c("n_dup_lines") > 3 * c("n_lines"), (c("n_dup_lines") == 0) & (c("n_lines") > 1)),
        "repeated_words": vote(5 * c("n_repeat_words") > w, 20 * c("n_repeat_words") <= w),
        "letters": vote(10 * c("n_letters") < 7 * c("word_chars"), 10 * c("n_letters") >= 9 * c("word_chars")),
        "line_ends": vote(10 * c("n_ended") < c("n_lines"), 2 * c("n_ended") >= c("n_lines")),
    }


def fit(patterns: np.ndarray, counts: np.ndarray, rounds: int = 200, tolerance: float = 1e-9) -> tuple[np.ndarray, float]:
    """What each rule says of good and of bad documents, and the share of good ones, by EM over vote patterns with counts.

    says[c, r, v]: probability that rule r votes v - 1 on a document of class c (1: good). A rule's accuracy on class c is
    thus says[c, r, 2c] over its votes there. The start trusts every rule alike; a bad vote never becomes evidence for
    good, nor the reverse, else the two classes would change names.
    """
    says, good = np.empty((2, patterns.shape[1], 3)), 0.8
    says[0], says[1] = START_BAD, START_GOOD
    total = counts.sum()
    if not total:
        return says, good
    told = np.stack([patterns == v for v in (-1, 0, 1)], 2).astype(float)
    for _ in range(rounds):
        p = posterior(patterns, says, good)
        new = np.stack([np.einsum("i,irv->rv", w * counts, told) + s * 20 for w, s in ((1 - p, START_BAD), (p, START_GOOD))])
        new /= new.sum(2, keepdims=True)
        new[0, :, 0], new[1, :, 2] = np.maximum(new[0, :, 0], new[1, :, 0]), np.maximum(new[1, :, 2], new[0, :, 2])
        new /= new.sum(2, keepdims=True)
        share = float(np.clip((p * counts).sum() / total, 0.01, 0.99))
        moved = max(np.abs(new - says).max(), abs(share - good))
        says, good = new, share
        if moved < tolerance:
            break
    return says, good


def accuracies(says: np.ndarray, good: float) -> np.ndarray:
    """Probability that each rule is right when it votes."""
    right = (1 - good) * says[0, :, 0] + good * says[1, :, 2]
    return right / (right + (1 - good) * says[0, :, 2] + good * says[1, :, 0])


def posterior(patterns: np.ndarray, says: np.ndarray, good: float) -> np.ndarray:
    """Probability that a document with each vote pattern is good."""
    at = patterns.astype(int) + 1
    ratio = np.log(says[1]) - np.log(says[0])
    score = np.log(good / (1 - good)) + ratio[np.arange(ratio.shape[0]), at].sum(1)
    return 1 / (1 + np.exp(-np.clip(score, -500, 500)))


def judge(docs: DataFrame, threshold: float = 0.5) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, quality, kept."""
    spark = docs.sparkSession
    rules = votes()
    code = sum(((rules[r] + 1) * 3**i for i, r in enumerate(RULES)), F.lit(0))
    seen = materialize(features(docs).withColumn("pattern", code.cast("int")), "quality")
    found = {r["pattern"]: r["n"] for r in seen.groupBy("pattern").agg(F.count("*").alias("n")).collect()}  # 3**len(RULES) rows at most
    codes = sorted(found)
    patterns = np.array([[k // 3**i % 3 - 1 for i in range(len(RULES))] for k in codes], np.float64).reshape(len(codes), len(RULES))
    says, good = fit(patterns, np.array([found[k] for k in codes], np.float64))
    table = spark.createDataFrame([(int(k), float(q)) for k, q in zip(codes, posterior(patterns, says, good), strict=True)], "pattern int, quality double")
    failed = base_failed()
    return seen.join(F.broadcast(table), "pattern").select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), "quality", (~failed & (F.col("quality") >= threshold)).alias("kept")
    )


def keep_good(docs: DataFrame, threshold: float = 0.5) -> DataFrame:
    """The documents that judge() keeps, with all their columns; a doc_id stays if every row of it was kept."""
    (bad,) = fresh(docs.columns, "bad")
    rejected = judge(docs, threshold).where(~F.col("kept")).select(F.col("doc_id").alias(bad)).distinct()
    return docs.join(rejected, F.col("doc_id").cast("bigint").eqNullSafe(F.col(bad)), "left_anti")
