"""Token ids by the tokenizers library, with a cache of pieces per Python worker.

No pre-token of either vocabulary reaches over a single space between two characters that are no white space, so columns
of texts are cut there (by Arrow, without Python strings), each distinct piece is encoded once and ids are gathered by
index. A new piece of common characters is cut into pre-tokens by the vocabulary's own rules for these characters, and each
distinct pre-token is merged once by the library's model (where white space is kept, many in one call); any other piece is
encoded by the library as a whole. Ids are the library's own for the whole text.
"""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Iterator
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import CACHES

#: Cached pieces and pre-tokens per worker; a cache starts anew beyond it. WORD_*: of a vocabulary of words, whose workers
#: also run where an executor's JVM has grown before; most pieces beyond so many are never met again.
PIECES, WORD_PIECES, WORD_PRETOKENS = 600_000, 150_000, 75_000
#: Rows encoded together at most, and bytes of text at most (one text may have more).
ROWS, BYTES, WORD_BYTES = 4000, 8 << 20, 1 << 20
#: Pre-tokens merged in one call of the library.
MERGED = 10_000

# Common characters beyond ASCII (letters that normalising leaves alone and whose lower case is one letter,
# and punctuation), and the pre-token patterns of the two kinds of vocabulary for texts of common characters.
_LETTERS = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u017f\u0400-\u045f"
_MARKS = "\u00a1\u00ab\u00bb\u00bf\u2013\u2014\u2018-\u201e\u2026"
_UNCOMMON = re.compile(rf"[^\x00-\x7f{_LETTERS}{_MARKS}]|<")  # "<": it may begin a special token
_PRE_WORD = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[0-9]|[^\t-\r 0-9{_LETTERS}]+")
_PRE_BYTE = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{_LETTERS}]+| ?[0-9]+| ?[^\t-\r 0-9{_LETTERS}]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+")
#: Texts of common characters that are a single pre-token, whatever is beside them (as Arrow's patterns are written).
_ONE_BYTE = rf"\A ?(?:[{_LETTERS}]+|[0-9]+|[^\t-\r 0-9{_LETTERS}]+)\z"
#: Punctuation after a letter or digit, which is a pre-token of its own in a vocabulary of words.
_ENDS, _ENDS_BYTE = r"([a-z0-9])([.,;:!?])", r"([A-Za-z0-9])([.,;:!?])"
#: A single line end before a letter, likewise where white space is kept.
_LINES = r"([!-~])\n([A-Za-z])"
#: Marks where pieces meet that keep their white space.
_SEAM = "\x00"
#: White space beside a space, or a seam: such texts are not simply cut at spaces.
_BESIDE = r"[\t-\r\x1c-\x1f\x85\p{Z}] | [\t-\r\x1c-\x1f\x85\p{Z}]|\x00"
#: Between pre-tokens that are merged together: in no common text, so its symbols are in none of theirs.
_APART = "\uffff"
_BLANK = re.compile(r"[\t-\r ]")
_BETWEEN = re.compile(r"(?<=\S)(?= \S)")

_known: dict[tuple[str, bool], CachedTokenizer] = {}
CACHES.append(_known)


def _symbols() -> dict[int, str]:
    """What byte-level vocabularies write for bytes that are not printed: the characters from 256 on, in order."""
    hidden = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255)]
    return {b: chr(256 + i) for i, b in enumerate(hidden)}


_SYMBOLS = _symbols()


def as_symbols(text: str) -> str:
    """The UTF-8 bytes of a text as byte-level vocabularies write them."""
    return text.encode("utf-8", "surrogatepass").decode("latin-1").translate(_SYMBOLS)


_APART_SYMBOLS = as_symbols(_APART)
_SYMBOL_OF = np.array([ord(_SYMBOLS.get(b, chr(b))) for b in range(256)], "<u4")


def is_common(text: str) -> bool:
    """Only common characters, and nothing that may be a special token: pretokens() holds for it."""
    return _UNCOMMON.search(text) is None


def pretokens(text: str) -> list[str]:
    """The words of a common text in a vocabulary of words, in lower case."""
    return _PRE_WORD.findall(text.lower())


def load(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


def groups(column: pa.Array, most: int = BYTES) -> Iterator[pa.Array]:
    """A string column in slices of ROWS rows and `most` bytes at most."""
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    upto, at = np.cumsum(size, dtype=np.int64), 0
    while at < len(column):
        before = upto[at] - size[at]
        end = max(at + 1, min(at + ROWS, int(np.searchsorted(upto, before + most, "right"))))
        yield column.slice(at, end - at)
        at = end


class CachedTokenizer:
    def __init__(self, path: str, words: bool):
        """words: the vocabulary drops white space and letter case; else a space belongs to the word after it."""
        self.tokenizer, self.by_words = load(path), words
        self.model = self.tokenizer.model
        self.most_pieces, self.most_bytes = (WORD_PIECES, WORD_BYTES) if words else (PIECES, BYTES)
        if not words:
            from tokenizers import Tokenizer, pre_tokenizers

            self.merging = Tokenizer(self.model)
            self.merging.pre_tokenizer = pre_tokenizers.Split(_APART_SYMBOLS, "removed")
            vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
            self.sizes = np.zeros(max(vocabulary.values(), default=0) + 1, np.int64)  # symbols of each id
            self.sizes[list(vocabulary.values())] = list(map(len, vocabulary))
        self._empty()

    def _empty(self) -> None:
        self.codes: dict[str, int] = {}
        self.pretokens: dict[str, bytes] = {}
        self.ids, self.used = np.empty(1 << 16, np.uint32), 0
        self.starts, self.lengths = np.empty(1 << 14, np.int64), np.empty(1 << 14, np.int64)

    def _encoded(self, pieces: list[str]) -> list[bytes]:
        """The ids of each piece, as their own four bytes."""
        known, merge = self.pretokens, self.model.tokenize
        cut = pretokens if self.by_words else _PRE_BYTE.findall
        out: list[bytes | None] = []
        whole: list[int] = []
        for i, p in enumerate(pieces):
            if _UNCOMMON.search(p):
                whole.append(i)
                out.append(None)
                continue
            ids = []
            for t in cut(p):
                own = known.get(t)
                if own is None:
                    if len(known) >= WORD_PRETOKENS:
                        known.clear()
                    own = known[t] = array("I", [x.id for x in merge(as_symbols(t))]).tobytes()
                ids.append(own)
            out.append(ids[0] if len(ids) == 1 else b"".join(ids))
        for at in range(0, len(whole), MERGED):
            some = whole[at : at + MERGED]
            for i, e in zip(some, self.tokenizer.encode_batch_fast([pieces[i] for i in some], add_special_tokens=False), strict=True):
                out[i] = array("I", e.ids).tobytes()
        return out

    def _merged(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of pre-tokens of common characters, and how many each has: where an id ends is told by its symbols."""
        ids, lengths = [], []
        for at in range(0, len(words), MERGED):
            some = _SYMBOL_OF[np.frombuffer(_APART.join(words[at : at + MERGED]).encode(), np.uint8)].tobytes().decode("utf-32-le")
            apart = some.split(_APART_SYMBOLS)
            ends = np.cumsum(np.fromiter(map(len, apart), np.int64, len(apart)))
            own = np.array(self.merging.encode_batch_fast([some], add_special_tokens=False)[0].ids, np.uint32)
            upto = np.cumsum(self.sizes[own])
            if not len(own) or upto[-1] != ends[-1]:  # a vocabulary that lacks symbols
                each = [[x.id for x in self.model.tokenize(w)] for w in apart]
                ids.append(np.array([i for e in each for i in e], np.uint32))
                lengths.append(np.fromiter(map(len, each), np.int64, len(each)))
                continue
            ids.append(own)
            lengths.append(np.diff(np.searchsorted(upto, ends) + 1, prepend=0))
        return np.concatenate(ids), np.concatenate(lengths)

    def _keep(self, pieces: list[str], ids: np.ndarray, lengths: np.ndarray) -> None:
        at, total = len(self.codes), len(ids)
        while at + len(pieces) > len(self.starts):
            self.starts, self.lengths = np.resize(self.starts, 2 * len(self.starts)), np.resize(self.lengths, 2 * len(self.lengths))
        while self.used + total > len(self.ids):
            self.ids = np.resize(self.ids, 2 * len(self.ids))
        self.starts[at : at + len(pieces)] = self.used + np.cumsum(lengths) - lengths
        self.lengths[at : at + len(pieces)] = lengths
        self.ids[self.used : self.used + total] = ids
        self.used += total
        self.codes.update(zip(pieces, range(at, at + len(pieces)), strict=True))

    def _learn(self, missing: list[str]) -> None:
        """Keeps the ids of distinct new pieces."""
        if not self.by_words:
            column, pieces = pa.array(missing, pa.large_string()), np.array(missing, object)
            odd, one = (pc.match_substring_regex(column, x).to_numpy(zero_copy_only=False) for x in (_UNCOMMON.pattern, _ONE_BYTE))
            single, missing = pieces[one & ~odd].tolist(), pieces[odd].tolist()
            if single:
                self._keep(single, *self._merged(single))
            several = [(p, _PRE_BYTE.findall(p)) for p in pieces[~(one | odd)].tolist()]
            new = [t for t in dict.fromkeys(chain.from_iterable(c for _, c in several)) if t not in self.codes]  # a pre-token is a piece, too
            if new:
                self._keep(new, *self._merged(new))
            several = [(p, c) for p, c in several if c != [p]]
            if several:
                codes = np.fromiter(map(self.codes.get, chain.from_iterable(c for _, c in several)), np.int64)
                ids, ends = self._gathered(codes, np.cumsum([0, *(len(c) for _, c in several)]))
                self._keep([p for p, _ in several], ids, np.diff(ends))
            if not missing:
                return
        found = self._encoded(missing)
        self._keep(missing, np.frombuffer(b"".join(found), np.uint32), np.fromiter(map(len, found), np.int64, len(found)) // 4)

    def _codes(self, pieces: list[str]) -> np.ndarray:
        codes = np.fromiter(map(self.codes.get, pieces, repeat(-1)), np.int64, len(pieces))
        missing = np.flatnonzero(codes < 0).tolist()
        if missing:
            new = [pieces[i] for i in missing]
            self._learn(new)
            codes[missing] = np.fromiter(map(self.codes.get, new), np.int64, len(new))
        return codes

    def _cut(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Codes of the pieces of texts (no nulls), and where the pieces of each text begin and end."""
        if self.by_words:
            cut = pc.ascii_split_whitespace(pc.replace_substring_regex(pc.ascii_lower(texts), _ENDS, r"\1 \2"))
        else:
            marked = pc.replace_substring(texts, " ", f"{_SEAM} ")
            for seam, parts in ((_ENDS_BYTE, rf"\1{_SEAM}\2"), (_LINES, f"\\1{_SEAM}\n{_SEAM}\\2")):
                marked = pc.replace_substring_regex(marked, seam, parts)
            cut = pc.split_pattern(marked, _SEAM)
        ends = cut.offsets.to_numpy().astype(np.int64)
        ends -= ends[0]
        coded = cut.flatten().dictionary_encode()
        names = coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        return (self._codes(names)[coded.indices.to_numpy(zero_copy_only=False)] if names else np.empty(0, np.int64)), ends

    def _gathered(self, codes: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        lengths = self.lengths[codes]
        upto = np.concatenate([[0], np.cumsum(lengths)])
        some = codes[lengths > 0]
        first, lengths = self.starts[some], self.lengths[some]
        places = np.ones(upto[-1], np.int64)  # steps from the place of one id to that of the next
        if len(some):
            places[0] = first[0]
            places[np.cumsum(lengths[:-1])] = first[1:] - first[:-1] - lengths[:-1] + 1
        return self.ids[np.cumsum(places, out=places)], upto[ends]

    def _group(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if len(self.codes) > self.most_pieces:
            self._empty()
        odd = (pc.match_substring(texts, "<|") if self.by_words else pc.match_substring_regex(texts, _BESIDE)).to_numpy(zero_copy_only=False)
        if not odd.any():
            return self._gathered(*self._cut(texts))
        parts: list[np.ndarray] = [np.empty(0, np.uint32)] * len(texts)
        plain = np.flatnonzero(~odd)
        if len(plain):
            ids, ends = self._gathered(*self._cut(texts.take(pa.array(plain))))
            for k, i in enumerate(plain.tolist()):
                parts[i] = ids[ends[k] : ends[k + 1]]
        for i in np.flatnonzero(odd).tolist():
            text = texts[i].as_py()
            codes = self._codes_of([p for p in _BLANK.split(text) if p] if self.by_words else _BETWEEN.split(text))
            parts[i] = self._gathered(codes, np.array([0, len(codes)]))[0]
        return np.concatenate(parts), np.concatenate([[0], np.cumsum([len(p) for p in parts])])

    def _codes_of(self, pieces: list[str]) -> np.ndarray:
        self._codes(list(dict.fromkeys(pieces)))
        return np.fromiter(map(self.codes.get, pieces), np.int64, len(pieces))

    def encode(self, column: pa.Array) -> Iterator[np.ndarray]:
        """The ids (uint32) of each text of a string column; null counts as empty."""
        for part in groups(column, self.most_bytes):
            ids, ends = self._group(pc.fill_null(part, ""))
            yield from np.split(ids, ends[1:-1])


def cached(path: str, words: bool) -> CachedTokenizer:
    """This worker's tokenizer for a vocabulary file."""
    if (path, words) not in _known:
        _known[path, words] = CachedTokenizer(path, words)
    return _known[path, words]
