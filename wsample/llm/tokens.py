"""Token ids and token counts of whole texts, from public vocabulary files whose path is a parameter.

Texts of Latin letters are cut into pre-tokens by the files' own rules, written for Python's ``re`` over the characters
whose classes no library version disputes; other texts are cut where no pre-token crosses (a single space between
visible characters, or any ASCII white space for word files) and the library cuts the pieces further.  A unit's ids
are made once a worker.  The cache of units is bounded: a full generation replaces the one before it.
"""

from __future__ import annotations

import functools
import heapq
import json
import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of

CACHE_ENTRIES = 500_000
#: Longer pieces are encoded but not kept.
CACHE_CHARS = 64
#: Between two visible characters; Python's idea of white space includes the libraries'.
_GAP = re.compile(r"(?<=\S) (?=\S)")
#: White space to Python but not to the library.
_ODD = ("\x1c", "\x1d", "\x1e", "\x1f")
_ASCII_SPACE = re.compile(r"[ \t\n\r\x0b\x0c]+")


class _Pieces(dict):
    """piece -> value, computed when neither generation has it."""

    def __init__(self, value):
        self.value, self.old = value, {}

    def __missing__(self, piece):
        made = self.old.get(piece)
        if made is None:
            made = self.value(piece)
        if len(piece) <= CACHE_CHARS:
            if len(self) >= CACHE_ENTRIES:
                self.old = dict(self)
                self.clear()
            self[piece] = made
        return made


#: The printable stand-ins of bytes in byte-level vocabularies: visible Latin-1 bytes stand for themselves.
_VISIBLE = [*range(33, 127), *range(161, 173), *range(174, 256)]
_STAND_IN = {b: chr(b) if b in _VISIBLE else chr(256 + [x for x in range(256) if x not in _VISIBLE].index(b)) for b in range(256)}


def byte_level(unit: str) -> str:
    return unit.encode().decode("latin-1").translate(_STAND_IN)


#: Letters and numerals below U+0250.
_L, _N = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\u024f", "0-9\xb2\xb3\xb9\xbc-\xbe"
_BYTE_UNITS = re.compile(rf" ?[{_L}]+|'(?:s|t|re|ve|m|ll|d)| ?[{_N}]+| ?[^\s{_L}{_N}]+|\s+(?!\S)|\s+").findall
_WORD_UNITS = re.compile(rf"[{_L}]+|'(?:s|t|re|ve|m|ll|d)|[{_N}]|[^\s{_L}{_N}]+").findall
_UNSURE = re.compile("[^\x00-\u024f]|[\u0130\x85\xa0]").search


def plain(text: str) -> bool:
    """Whether the rules above cut the text as the libraries do: no special string, and no character beyond doubt."""
    return "<|" not in text and not any(c in text for c in _ODD) and (text.isascii() or not _UNSURE(text))


def lowered(text: str) -> str | None:
    """The text in lower case where the rules above cut that as the word files' libraries do.

    Some Latin capitals have their lower case beyond U+024F, so it is the lower-cased text that must be beyond doubt.
    """
    if not plain(text):
        return None
    low = text.lower()
    return low if low.isascii() or not _UNSURE(low) else None


class ByteLevelIds:
    """Ids of a byte-level vocabulary as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        library = Tokenizer.from_file(path)
        self.encode, self.tokenize = library.encode, library.model.tokenize
        self.units, self.pieces = _Pieces(self.unit_ids), _Pieces(self.piece_ids)

    def unit_ids(self, unit: str) -> bytes:
        return array("I", [t.id for t in self.tokenize(byte_level(unit))]).tobytes()

    def piece_ids(self, piece: str) -> bytes:
        return array("I", self.encode(piece, add_special_tokens=False).ids).tobytes()

    def __call__(self, text: str) -> bytes:
        if plain(text):
            return b"".join(map(self.units.__getitem__, _BYTE_UNITS(text)))
        first, *rest = _GAP.split(text)
        return b"".join([self.pieces[first], *[self.pieces[" " + x] for x in rest]])


def words_of(text: str) -> list[str]:
    """Pieces between ASCII white space."""
    if any(c in text for c in _ODD):
        return [x for x in _ASCII_SPACE.split(text) if x]
    return text.split()


class WordIds(ByteLevelIds):
    """Ids of a lower-case vocabulary with word ends, white space being dropped."""

    def __call__(self, text: str) -> bytes:
        if (low := lowered(text)) is not None:
            return b"".join(map(self.units.__getitem__, _WORD_UNITS(low)))
        return b"".join([self.pieces[x] for x in words_of(text)])


class MergeCounter:
    """Tokens of a text by byte-pair merging, without making ids.

    A pre-token is a linked list of symbols with a heap of its adjacent pairs by merge rank.
    The lowest pair is merged until none is left; each merge takes one off the initial count.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pairs = [tuple(x.split(" ")) if isinstance(x, str) else tuple(x) for x in spec["model"]["merges"]]
        self.rank = {p: i for i, p in enumerate(pairs)}
        self.end = spec["model"].get("end_of_word_suffix") or ""
        library = Tokenizer.from_file(path)
        self.normal, self.split = library.normalizer, library.pre_tokenizer
        special = [re.escape(x["content"]) for x in spec["added_tokens"]]
        self.special = re.compile("|".join(special)) if special else None
        self.pieces = _Pieces(self.count_piece)
        self.units = _Pieces(self.count_unit)

    def __call__(self, text: str) -> int:
        if (low := lowered(text)) is not None:
            return sum(map(self.units.__getitem__, _WORD_UNITS(low)))
        return sum([self.pieces[x] for x in words_of(text)])

    def count_piece(self, piece: str) -> int:
        """A piece without white space: special strings count one each, the rest is cut by the file's rules."""
        if self.special is None or "<" not in piece:
            return self._ordinary(piece)
        return len(self.special.findall(piece)) + sum(self._ordinary(x) for x in self.special.split(piece) if x)

    def _ordinary(self, piece: str) -> int:
        normal = self.normal.normalize_str(piece) if self.normal else piece
        return sum(self.count_symbols(unit) for unit, _ in self.split.pre_tokenize_str(normal))

    def count_unit(self, unit: str) -> int:
        return self.count_symbols(byte_level(unit))

    def count_symbols(self, unit: str) -> int:
        return count_after_merges([*unit[:-1], unit[-1] + self.end] if unit else [], self.rank)


def count_after_merges(symbols: list[str], rank: dict[tuple[str, str], int]) -> int:
    """Initial symbols minus merges; equal ranks go left to right."""
    n = len(symbols)
    if n < 2:
        return n
    after, before, alive = [*range(1, n), -1], [-1, *range(n - 1)], [True] * n
    heap = [(r, i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (r := rank.get((symbols[i], symbols[i + 1]))) is not None]
    heapq.heapify(heap)
    merges = 0
    while heap:
        _, i, left, right = heapq.heappop(heap)
        j = after[i]
        if not alive[i] or j < 0 or symbols[i] != left or symbols[j] != right:
            continue
        symbols[i], alive[j] = left + right, False
        merges += 1
        k = after[i] = after[j]
        if k >= 0:
            before[k] = i
            if (r := rank.get((symbols[i], symbols[k]))) is not None:
                heapq.heappush(heap, (r, i, symbols[i], symbols[k]))
        h = before[i]
        if h >= 0 and (r := rank.get((symbols[h], symbols[i]))) is not None:
            heapq.heappush(heap, (r, h, symbols[h], symbols[i]))
    return n - merges


@functools.lru_cache(maxsize=4)
def encoder(kind: str, path: str):
    """One encoder a worker process and file."""
    return {"byte": ByteLevelIds, "word": WordIds, "count": MergeCounter}[kind](path)


def crc(ids: bytes) -> int:
    return zlib.crc32(ids) & 0xFFFFFFFF


def token_counts(docs: DataFrame, path: str, *, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Bytes and tokens of every whole text, and whether the tokens pass ``limit``.

    A null or empty text has none.  One row an input row, repeated rows included; other columns are not read.
    """

    def count(batch: pa.RecordBatch) -> pa.RecordBatch:
        counter = encoder("count", path)
        texts = batch.column(1).to_pylist()
        n = np.fromiter(map(counter, texts), dtype=np.int64, count=len(texts))
        size = pa.compute.binary_length(batch.column(1)).cast(pa.int64())
        return pa.RecordBatch.from_arrays([batch.column(0), size, pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    kind = docs.schema[id_col].dataType.simpleString()
    return by_batch(docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")), count, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean", size_by="text")
