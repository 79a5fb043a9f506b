"""Byte-pair encoding by dynamic programming over prefixes.

The encoding of every prefix of a word ends in one token that is unique, and a token may follow another exactly if the
pair of them is its own encoding. So one pass over a word stores each prefix's last token: the automaton of the vocabulary
with its suffix links (Aho-Corasick) gives the tokens that end at a position, longest first, and the first one that may
follow the last token of the prefix before it is stored. Following the stored tokens back from the end gives the ids, the same that merging by rank
gives. Whether a pair stands is decided by undoing merges, youngest first, at the seam, and remembered.

Word ends are part of a word's last symbol. Normalising and cutting into words is done by the vocabulary's own normaliser
and pre-tokenizer, for pieces of common characters by the same rules as one pattern; special tokens in a text stay whole,
as in the library. Words are encoded once per worker.

Defined results: null text counts as empty (no ids, empty decoded text); repeated rows are encoded alike; extra columns
are ignored; an empty table gives no rows; texts are read whole.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CACHES, with_columns_only
from .tokens import as_symbols, is_common, load, pretokens

WORDS = 600_000
_END = "\x00"
_known: dict[str, Bpe] = {}
CACHES.append(_known)


class Bpe:
    """Encoder for a vocabulary file of the tokenizers library whose model is byte-level BPE with a word-end mark."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        model = told["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        self.library = load(path)
        self.common = self._plain_by_pattern(told)
        self.special = {t["content"]: t["id"] for t in told["added_tokens"] if t["content"]}
        self._cut = re.compile("|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True))) if self.special else None
        vocab: dict[str, int] = model["vocab"]
        self.names = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        # Tokens are numbered by age: symbols first, then merges as they were learned.
        made: dict[str, tuple[str, str]] = {}
        for a, b in merges:
            made.setdefault(a + b, (a, b))
        symbols = sorted((t for t in vocab if t not in made and t not in self.special), key=vocab.get)
        age = {t: i for i, t in enumerate([*symbols, *made])}
        self.id_of = [vocab[t] for t in age]
        self.merged = {}
        for a, b in merges:
            if made[a + b] == (a, b):
                self.merged[age[a], age[b]] = age[a + b]
        self.left, self.right = list(range(len(age))), list(range(len(age)))
        for t, (a, b) in made.items():
            self.left[age[t]], self.right[age[t]] = age[a], age[b]
        self.automaton = ahocorasick.Automaton()
        for t, i in age.items():
            ended = self.suffix and t.endswith(self.suffix)
            bare = t[: -len(self.suffix)] + _END if ended else t
            if bare not in ("", _END):
                self.automaton.add_word(bare, (i, len(bare)))
        self.automaton.make_automaton()
        self.pairs: dict[int, bool] = {}
        self.whole: dict[int, bool] = {}
        self.words: dict[str, tuple[str, int, str]] = {}
        self.entries: dict[str, tuple[str, int, str]] = {}

    @staticmethod
    def _plain_by_pattern(told: dict) -> bool:
        """The vocabulary normalises and cuts as tokens.pretokens() does."""
        kinds = [n.get("type") for n in (told.get("normalizer") or {}).get("normalizers", [])]
        steps = [p.get("type") for p in (told.get("pre_tokenizer") or {}).get("pretokenizers", [])]
        cut = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
        return kinds == ["NFC", "Replace", "Lowercase"] and steps == ["Split", "ByteLevel"] and told["pre_tokenizer"]["pretokenizers"][0]["pattern"].get("Regex") == cut

    def stands(self, one: int, two: int) -> bool:
        """The pair is its own encoding: no merge reaches over the seam before both are made."""
        key = one << 32 | two
        known = self.pairs.get(key)
        if known is not None:
            return known
        left, right, merged = self.left, self.right, self.merged
        a, b, limit, good = one, two, len(left), True
        while True:
            over = merged.get((a, b))
            if over is not None and over < limit:
                good = False
                break
            # The younger of the two was made last: look at the seam as it was before that.
            if a > b:
                limit, a = a, right[a]
                if a != limit:
                    continue
                limit, older = b + 1, left[b]
                if older == b:
                    break
                b = older
            else:
                limit, older = b + 1, left[b]
                if older != b:
                    b = older
                    continue
                limit, older = a, right[a]
                if older == a:
                    break
                a = older
        if len(self.pairs) > 4_000_000:
            self.pairs.clear()
        self.pairs[key] = good
        return good

    def makes_itself(self, token: int) -> bool:
        """The token is the encoding of its own text."""
        known = self.whole.get(token)
        if known is None:
            a, b = self.left[token], self.right[token]
            known = self.whole[token] = a == token or (self.makes_itself(a) and self.makes_itself(b) and self._first_over(a, b) == token)
        return known

    def _first_over(self, a: int, b: int) -> int | None:
        """The merge that joins two tokens, if none crosses their seam before."""
        over = self.merged.get((a, b))
        if over is None:
            return None
        del self.merged[a, b]
        self.pairs.pop(a << 32 | b, None)
        alone = self.stands(a, b)
        self.pairs.pop(a << 32 | b, None)
        self.merged[a, b] = over
        return over if alone else None

    def word(self, word: str) -> list[int]:
        """Ids of one word of byte-level symbols."""
        text = word + _END if self.suffix else word
        skip = len(word) if self.suffix else -1  # the last letter and the word's end are one symbol
        last, size = [-1] * (len(text) + 1), [0] * (len(text) + 1)
        pairs = self.pairs
        for at, (token, length) in self.automaton.iter(text):  # at each end, longer tokens come first
            end = at + 1
            if last[end] >= 0 or end == skip:
                continue
            start = end - length
            if start:
                before = last[start]
                if before < 0:
                    continue
                good = pairs.get(before << 32 | token)
                if good is None:
                    good = self.stands(before, token)
            else:
                good = self.makes_itself(token)
            if good:
                last[end], size[end] = token, length
        out, at = [], len(text)
        while at > 0:
            if last[at] < 0:
                return self._merge(word)
            out.append(self.id_of[last[at]])
            at -= size[at]
        return out[::-1]

    def _merge(self, word: str) -> list[int]:
        """By rank, for a word with a symbol that the vocabulary lacks."""
        return [t.id for t in self.library.model.tokenize(word)]

    def _entry(self, word: str) -> tuple[str, int, str]:
        found = self.entries.get(word)
        if found is None:
            if len(self.entries) > WORDS:
                self.entries.clear()
            ids = self.word(word)
            found = self.entries[word] = " ".join(map(str, ids)), len(ids), " ".join([self.names[i] for i in ids])
        return found

    def _plain(self, text: str) -> list[str]:
        if self.common and is_common(text):
            return [as_symbols(w) for w in pretokens(text)]
        normal = self.library.normalizer.normalize_str(text) if self.library.normalizer else text
        return [w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(normal)]

    def encode(self, text: str) -> tuple[str, int, str]:
        """Ids as decimals joined by spaces, how many, and the decoded text."""
        out: list[tuple[str, int, str]] = []
        at = 0
        for m in self._cut.finditer(text) if self._cut and "<" in text else ():
            out += self._words(text[at : m.start()])
            out.append((str(self.special[m[0]]), 1, m[0]))
            at = m.end()
        out += self._words(text[at:] if at else text)
        return " ".join(w[0] for w in out if w[1]), sum(w[1] for w in out), " ".join(w[2] for w in out if w[1])

    def _words(self, text: str) -> list[tuple[str, int, str]]:
        """Entries of all words of a text without special tokens; pieces between spaces are looked up whole."""
        pieces = text.replace("\n", " ").split(" ")
        get = self.words.get
        found = [get(p) for p in pieces]
        if None in found:
            if len(self.words) > WORDS:
                self.words.clear()
            new = {p: self._whole(p) for p, f in zip(pieces, found, strict=True) if f is None}
            self.words |= new
            found = [f or new[p] for p, f in zip(pieces, found, strict=True)]
        return found

    def _whole(self, piece: str) -> tuple[str, int, str]:
        made = [self._entry(w) for w in self._plain(piece)] if piece else []
        return made[0] if len(made) == 1 else (" ".join([m[0] for m in made]), sum(m[1] for m in made), " ".join([m[2] for m in made]))


def encoder(path: str) -> Bpe:
    if path not in _known:
        _known[path] = Bpe(path)
    return _known[path]


def _encode(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for b in batches:
            n, ids, text = [], [], []
            for t in b.column("text"):
                told, count, decoded = bpe.encode(t.as_py() or "")
                n.append(count)
                ids.append(hashlib.sha256(told.encode()).hexdigest())
                text.append(hashlib.sha256(decoded.encode("utf-8", "surrogatepass")).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(text, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: one row per row of docs."""
    d = with_columns_only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("bigint"))
    return d.mapInArrow(_encode(path), "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")


def _ids(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(path)
        for b in batches:
            made = [bpe.encode(t.as_py() or "") for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([[int(i) for i in m[0].split()] for m in made], pa.list_(pa.int32())), pa.array([m[2] for m in made], pa.string())], ["doc_id", "ids", "decoded"])

    return run


def encode(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, ids, decoded."""
    d = with_columns_only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("bigint"))
    return d.mapInArrow(_ids(path), "doc_id bigint, ids array<int>, decoded string")
