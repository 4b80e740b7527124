"""Benchmark decontamination by winnowing.

Of every window of w successive k-gram hashes the least is kept (the last of equals), on both sides.  A span of
w + k - 1 words that two texts share holds a whole window, so both keep the same hash of it: no such span is
missed.  Kept hashes that meet name a diagonal of the two texts, which is compared word by word.
"""

from __future__ import annotations

import functools
import hashlib
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of

SPAN, K = 10, 5
#: Benchmark text that is held in memory at once; a larger benchmark is taken in blocks, one pass over the documents each.
BLOCK_BYTES = 16_000_000
_MULTIPLY = np.uint64(0x9E3779B97F4A7C15)
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Bytes of words: digits, lower-case letters, and all of characters beyond ASCII.
_WORD = np.array([48 <= c <= 57 or 97 <= c <= 122 or c > 127 for c in range(256)])


@functools.lru_cache(maxsize=1)
def _powers(n: int) -> np.ndarray:
    return np.multiply.accumulate(np.concatenate([[np.uint64(1)], np.full(n - 1, 0x100000001B3, np.uint64)]))


@dataclass
class Words:
    """Words of several texts on end: their bytes' places, hashes, and each text's first word."""

    data: bytes
    start: np.ndarray
    end: np.ndarray
    code: np.ndarray
    first: np.ndarray  # one more than texts

    def of(self, lo: int, hi: int) -> list[bytes]:
        return [self.data[a:b] for a, b in zip(self.start[lo:hi].tolist(), self.end[lo:hi].tolist(), strict=True)]


def words_of(texts: list[str]) -> Words:
    raw = [x.encode() for x in texts]
    data = (b"\n".join(raw) + b"\n").translate(_LOWER)
    b = np.frombuffer(data, np.uint8)
    edge = np.flatnonzero(np.diff(np.concatenate([[False], _WORD[b], [False]]).astype(np.int8)))
    start, end = edge[::2], edge[1::2]
    if len(start):
        size = end - start
        inside = np.flatnonzero(_WORD[b])
        offset = np.cumsum(size) - size
        place = np.arange(len(inside)) - np.repeat(offset, size)
        code = np.add.reduceat((b[inside].astype(np.uint64) + np.uint64(1)) * _powers(1 << int(size.max()).bit_length())[place], offset)
        code ^= code >> np.uint64(31)
        code *= np.uint64(0xBF58476D1CE4E5B9)
        code ^= code >> np.uint64(29)
    else:
        code = np.zeros(0, np.uint64)
    bounds = np.cumsum([0, *(len(x) + 1 for x in raw)])
    return Words(data, start, end, code, np.searchsorted(start, bounds))


def grams(code: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k words from each on."""
    n = len(code) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h = h * _MULTIPLY + code[j : j + n]
    h ^= h >> np.uint64(32)
    return h * np.uint64(0x94D049BB133111EB)


def winnowed(h: np.ndarray, w: int) -> np.ndarray:
    """Places of the kept hashes: of each window of w the least, the last of equals."""
    n = len(h) - w + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    least, place = h[:n].copy(), np.arange(n)
    for j in range(1, w):
        now = h[j : j + n]
        lower = now <= least
        least[lower] = now[lower]
        place[lower] = np.flatnonzero(lower) + j
    return np.unique(place)


@dataclass
class Index:
    """Fingerprints of benchmark items."""

    span: int
    k: int
    items: list[tuple[str, np.ndarray, list[bytes]]] = field(default_factory=list)
    kept: dict[int, list[tuple[int, int]]] = field(default_factory=lambda: defaultdict(list))
    short: dict[int, dict[int, list[int]]] = field(default_factory=dict)
    table: np.ndarray | None = None

    def add(self, name: str, text: str) -> None:
        words = words_of([text])
        n = len(words.code)
        if not n:
            return
        self.items.append((name, words.code, words.of(0, n)))
        if n < self.span:
            self.short.setdefault(n, defaultdict(list))[int(grams(words.code, n)[0])].append(len(self.items) - 1)
        else:
            h = grams(words.code, self.k)
            for q in winnowed(h, self.span - self.k + 1).tolist():
                self.kept[int(h[q])].append((len(self.items) - 1, q))

    def close(self) -> Index:
        self.table = np.array(sorted(self.kept), np.uint64)
        return self


def _within(h: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Which hashes are in a sorted table."""
    if not len(table) or not len(h):
        return np.zeros(len(h), bool)
    at = np.searchsorted(table, h)
    return table[np.minimum(at, len(table) - 1)] == h


def find(words: Words, index: Index) -> list[tuple[list[tuple[int, int]], set[str]]]:
    """For each text its hit runs of words (from 0, end exclusive) and the items with windows in it."""
    out: list[tuple[list[tuple[int, int]], set[str]]] = [([], set()) for _ in range(len(words.first) - 1)]
    h = grams(words.code, index.k)
    kept = winnowed(h, index.span - index.k + 1)
    kept = kept[_within(h[kept], index.table)]
    text_of_ = np.searchsorted(words.first, kept, side="right") - 1
    seen: set[tuple[int, int, int]] = set()
    for p, t in zip(kept.tolist(), text_of_.tolist(), strict=True):
        for item, q in index.kept[int(h[p])]:
            if (t, item, p - q) in seen:
                continue
            seen.add((t, item, p - q))
            name, code, spelled = index.items[item]
            lo, hi = max(int(words.first[t]), p - q), min(int(words.first[t + 1]), p - q + len(code))
            same = np.concatenate([[False], words.code[lo:hi] == code[lo - p + q : hi - p + q], [False]]).astype(np.int8)
            edge = np.flatnonzero(np.diff(same))
            for a, b in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
                if b - a >= index.span and words.of(lo + a, lo + b) == spelled[lo + a - p + q : lo + b - p + q]:
                    out[t][0].append((lo + a - int(words.first[t]), lo + b - int(words.first[t])))
                    out[t][1].add(name)
    for n, lookup in index.short.items():
        h = grams(words.code, n)
        for p in np.flatnonzero(_within(h, np.array(sorted(lookup), np.uint64))).tolist():
            t = int(np.searchsorted(words.first, p, side="right")) - 1
            if p + n > words.first[t + 1]:
                continue
            for item in lookup[int(h[p])]:
                if words.of(p, p + n) == index.items[item][2]:
                    out[t][0].append((p - int(words.first[t]), p + n - int(words.first[t])))
                    out[t][1].add(index.items[item][0])
    return out


def indexes(benchmark: DataFrame, *, span: int, k: int, block_bytes: int, item_col: str, item_text: str) -> list[Broadcast]:
    """Indexes of the benchmark's blocks, one at least; each holds about ``block_bytes`` of text whatever the benchmark's size."""
    spark = benchmark.sparkSession
    items = benchmark.where(F.col(item_col).isNotNull()).select(F.col(item_col).cast("string").alias("name"), text_of(item_text).alias("text"))
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks, made = max(1, -(-size // block_bytes)), []
    for b in range(blocks):
        index = Index(span, k)
        for r in items.where(F.pmod(F.xxhash64("name"), F.lit(blocks)) == b).toLocalIterator():
            index.add(r["name"], r["text"])
        made.append(spark.sparkContext.broadcast(index.close()))
    return made


def hits(docs: DataFrame, benchmark: DataFrame, *, span: int = SPAN, k: int = K, block_bytes: int = BLOCK_BYTES, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id, n_words, spans, items): words of each whole text, its hit runs (flat: start, end, ...), and the items hit, as strings.

    A run of ``span`` successive words of an item is a hit wherever it stands; an item of fewer words is one run.
    Null texts have no words and null items no name.  Runs of different blocks may overlap.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    now = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text"), F.lit(0).cast("long").alias("n_words"), F.array().cast("array<int>").alias("spans"), F.array().cast("array<string>").alias("items"))
    made = indexes(benchmark, span=span, k=k, block_bytes=block_bytes, item_col=item_col, item_text=item_text)
    for b, shared in enumerate(made):
        last = b == len(made) - 1

        def scan(batch: pa.RecordBatch, shared=shared, last=last) -> pa.RecordBatch:
            words = words_of(batch.column("text").to_pylist())
            spans, names = batch.column("spans").to_pylist(), batch.column("items").to_pylist()
            for i, (runs, found) in enumerate(find(words, shared.value)):
                if runs:
                    spans[i] = [*spans[i], *(x for run in runs for x in run)]
                    names[i] = sorted({*names[i], *found})
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([""] * batch.num_rows) if last else batch.column("text"), pa.array(np.diff(words.first), pa.int64()), pa.array(spans, pa.list_(pa.int32())), pa.array(names, pa.list_(pa.string()))], ["doc_id", "text", "n_words", "spans", "items"])

        now = by_batch(now, scan, f"doc_id {kind}, text string, n_words long, spans array<int>, items array<string>", size_by="text")
    return now.drop("text")


def contamination(docs: DataFrame, benchmark: DataFrame, **kw) -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, items_sha256, contaminated), one row a document."""
    found = hits(docs, benchmark, **kw)

    def digest(batch: pa.RecordBatch) -> pa.RecordBatch:
        n_hit, n_items, names = [], [], []
        for spans, items in zip(batch.column("spans").to_pylist(), batch.column("items").to_pylist(), strict=True):
            total = reach = 0
            for lo, hi in sorted(zip(spans[::2], spans[1::2], strict=True)):
                total += max(0, hi - max(lo, reach))
                reach = max(reach, hi)
            n_hit.append(total)
            n_items.append(len(items))
            names.append(hashlib.sha256(",".join(sorted(items)).encode()).hexdigest())
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_words"), pa.array(n_hit, pa.int64()), pa.array(n_items, pa.int64()), pa.array(names), pa.array([x > 0 for x in n_hit])], ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    kind = found.schema["doc_id"].dataType.simpleString()
    return by_batch(found, digest, f"doc_id {kind}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def clean(docs: DataFrame, benchmark: DataFrame, *, span: int = SPAN, k: int = K, block_bytes: int = BLOCK_BYTES, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows without a hit, with all their columns.  A null text has no hit."""
    for shared in indexes(benchmark, span=span, k=k, block_bytes=block_bytes, item_col=item_col, item_text=item_text):

        def keep(batch: pa.RecordBatch, shared=shared) -> pa.RecordBatch:
            words = words_of([x or "" for x in batch.column(text_col).to_pylist()])
            return batch.filter(pa.array([not runs for runs, _ in find(words, shared.value)], pa.bool_()))

        docs = by_batch(docs, keep, docs.schema, size_by=text_col)
    return docs
