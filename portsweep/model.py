"""Ids, read orders, memory limits and bounded folds of the sweep model.

In a round a vertex sweeps its ports: it reads each in-buffer at most once and writes each out-buffer at most once, with
little memory in between. Here a round is one set-oriented step over all vertices; messages are rows.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import ceil, log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A vertex id is kind * SPAN + key.
SPAN = 10**12
KINDS = {k: i for i, k in enumerate(("world", "region", "nation", "customer", "supplier", "order", "part", "user", "event", "conversation", "turn", "document", "source", "language", "page", "link"))}

PORTS = T.StructType([T.StructField(c, T.LongType()) for c in ("src", "port", "dst", "rev_port")] + [T.StructField("alive", T.BooleanType())])
MESSAGES = T.StructType(
    [T.StructField(c, T.LongType()) for c in ("round", "src", "dst", "port", "rev_port")]
    + [T.StructField("kind", T.StringType()), T.StructField("a", T.LongType()), T.StructField("b", T.LongType()), T.StructField("flag", T.BooleanType()), T.StructField("path", T.ArrayType(T.LongType()))]
)


def vid(kind: str, key: Column | str | int) -> Column:
    """The id of the vertex of a kind with a key."""
    key = F.lit(key) if isinstance(key, int) else F.col(key) if isinstance(key, str) else key
    return key.cast("bigint") + F.lit(KINDS[kind] * SPAN)


# Fixed values of the arithmetic hash, simple enough to repeat in any SQL dialect.
_P, _A, _B, _C = 2147483647, 48271, 69621, 40692


class ReadOrder:
    """In which order a vertex reads its ports: a column over (reader, port, round), least first."""

    def __init__(self, key: Callable[[Column, Column, Column], Column]):
        self.key = key

    @classmethod
    def ascending_port(cls) -> ReadOrder:
        return cls(lambda reader, port, turn: port)

    @classmethod
    def descending_port(cls) -> ReadOrder:
        return cls(lambda reader, port, turn: -port)

    @classmethod
    def adversarial(cls, key: Callable[[Column, Column, Column], Column]) -> ReadOrder:
        """Any permutation the caller names."""
        return cls(key)

    @classmethod
    def random(cls, seed: int) -> ReadOrder:
        """A permutation per reader and round that any engine can recompute; ties fall to the port."""
        return cls(lambda reader, port, turn: F.struct((F.pmod(reader, F.lit(_P)) * _A + port * _B + turn * _C + seed) % _P, port))

    @classmethod
    def strong(cls, key: Callable[[Column, Column, Column], Column]) -> ReadOrder:
        """As adversarial; the column may also use state columns of the reader (prefixed state_)."""
        return cls(key)


class LimitError(AssertionError):
    """A protocol used more memory or larger messages than its limits allow."""


@dataclass(frozen=True)
class SweepLimits:
    """B bits of memory per vertex and S bits per message, S <= B; None: unlimited."""

    memory: float | None
    message: float | None
    n: int

    def __post_init__(self) -> None:
        if self.memory is not None and self.message is not None and self.message > self.memory:
            raise ValueError("a message must fit in memory")

    @classmethod
    def classical(cls, n: int) -> SweepLimits:
        """Unlimited memory and messages."""
        return cls(None, None, n)

    @classmethod
    def congested(cls, n: int, words: int = 8) -> SweepLimits:
        """Unlimited memory, messages of O(log n) bits."""
        return cls(None, words * word_bits(n), n)

    @classmethod
    def compact(cls, n: int, words: int = 8) -> SweepLimits:
        """O(log n) bits for both."""
        return cls(words * word_bits(n), words * word_bits(n), n)

    @classmethod
    def polylog(cls, n: int, words: int = 8) -> SweepLimits:
        """O(log^2 n) bits of memory, messages of O(log n) bits."""
        return cls(words * word_bits(n) ** 2, words * word_bits(n), n)

    def enforce(self, memory_words: int, message_words: int) -> None:
        bits = word_bits(self.n)
        if self.memory is not None and memory_words * bits > self.memory:
            raise LimitError(f"{memory_words} words of memory exceed {self.memory} bits")
        if self.message is not None and message_words * bits > self.message:
            raise LimitError(f"a message of {message_words} words exceeds {self.message} bits")


def word_bits(n: int) -> int:
    """Bits of one id among n."""
    return max(1, ceil(log2(max(2, n))))


@dataclass(frozen=True)
class BoundedFold:
    """A vertex's local computation over the messages it reads: an aggregate with a fixed number of words of state.

    Folds whose result does not depend on the order are one built-in aggregate (with map-side combining); folds that keep
    the first or last message of a read order are min_by or max_by over it.
    """

    name: str
    column: Callable[[Column, Column], Column]
    words: int = 1

    def over(self, messages: DataFrame, reader: str = "dst", value: str = "a", port: str = "rev_port", turn: str = "round", order: ReadOrder | None = None) -> DataFrame:
        key = (order or ReadOrder.ascending_port()).key(F.col(reader), F.col(port), F.col(turn))
        return messages.groupBy(reader).agg(self.column(F.col(value), key).alias(self.name))


FOLDS = {
    "max": BoundedFold("max", lambda v, k: F.max(v)),
    "min": BoundedFold("min", lambda v, k: F.min(v)),
    "sum": BoundedFold("sum", lambda v, k: F.sum(v)),
    "count": BoundedFold("count", lambda v, k: F.count(v)),
    "first": BoundedFold("first", lambda v, k: F.min_by(v, k), 2),
    "last": BoundedFold("last", lambda v, k: F.max_by(v, k), 2),
}
