"""Content-addressed store of token id streams.

A rolling hash cuts each document's ids into chunks where its content says so, so that equal passages make
equal chunks wherever they stand.  A chunk is stored once, under its digest.  A document is a recipe of
digests; a Merkle root over the recipe and the digests of the stored bytes verify reconstruction.

Layout under one folder: ``chunks`` (digest, n_ids, width, payload), ``recipes`` (file_no, row_no, doc_id,
n_tokens, start_in_file, root, chunks), files of recipes in ascending doc_id order, and ``manifest``
(file_no, n_docs, n_tokens, root) with a Merkle root over each file's documents.
"""

from __future__ import annotations

import functools
import hashlib
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, new_path, text_of, written
from wsample.llm.tokens import encoder

#: Ids a chunk: least, most, and the mean between least and a cut as a power of two.
LEAST, MOST, MEAN_BITS = 128, 2048, 9
DIGEST_BYTES = 16
#: Digests that a task remembers having written.
REMEMBERED = 500_000
RECIPE = "array<struct<digest:binary,n_ids:int>>"


def cuts(ids: np.ndarray) -> list[int]:
    """Ends of the chunks: where a rolling hash of the last 16 ids has its top bits clear, within the bounds on size."""
    if not len(ids):
        return []
    h = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    for step in (1, 2, 4, 8):  # sums over 2, 4, 8 and 16 ids, older ones shifted further
        shifted = np.zeros_like(h)
        shifted[step:] = h[:-step] << np.uint64(step)
        h = h + shifted
    ends, last = [], 0
    for at in (np.flatnonzero(h >> np.uint64(64 - MEAN_BITS) == 0) + 1).tolist():
        while at - last > MOST:
            last += MOST
            ends.append(last)
        if at - last >= LEAST:
            last = at
            ends.append(last)
    while len(ids) - last > MOST:
        last += MOST
        ends.append(last)
    if last < len(ids):
        ends.append(len(ids))
    return ends


def digest(data: bytes) -> bytes:
    return hashlib.sha256(data).digest()[:DIGEST_BYTES]


def merkle_root(leaves: list[bytes]) -> bytes:
    """Root of a binary hash tree; an odd node goes up unchanged; nothing has the digest of nothing."""
    level = list(leaves) or [digest(b"")]
    while len(level) > 1:
        level = [digest(b"\x01" + level[i] + level[i + 1]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    return level[0]


@functools.lru_cache(maxsize=4096)
def _advance(n_bytes: int) -> tuple[int, ...]:
    """What ``n_bytes`` zero bytes do to each bit of a CRC-32."""
    base = zlib.crc32(bytes(n_bytes), 0)
    return tuple(zlib.crc32(bytes(n_bytes), 1 << i) ^ base for i in range(32))


def join_crc(first: int, second: int, second_bytes: int) -> int:
    """CRC-32 of two runs of bytes from their own."""
    for bit in _advance(second_bytes):
        if first & 1:
            second ^= bit
        first >>= 1
    return second


@dataclass(frozen=True)
class Store:
    chunks: DataFrame
    recipes: DataFrame
    manifest: DataFrame
    path: str


def write_store(docs: DataFrame, path: str, *, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", folder: str | None = None) -> Store:
    """Encode whole texts, append the end id, and write chunks, recipes and manifest.

    A null text is empty.  Null ids come first; rows with equal ids stay apart, in the order of their roots.
    """
    spark = docs.sparkSession
    folder = folder or new_path(spark, "store")
    kind = docs.schema[id_col].dataType.simpleString()

    def encode(batches):
        tokens, end, seen = encoder("word", path), np.array([end_id], dtype="<u4").tobytes(), set()
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo in range(0, len(texts), 256):
                counts, roots, recipe, names, sizes, fresh, new_names, new_sizes, payloads = [], [], [0], [], [], [0], [], [], []
                for text in texts[lo : lo + 256]:
                    data = tokens(text) + end
                    at, leaves = 0, []
                    for to in cuts(np.frombuffer(data, dtype="<u4")):
                        part = data[4 * at : 4 * to]
                        name = digest(part)
                        leaves.append(name)
                        sizes.append(to - at)
                        if name not in seen:
                            if len(seen) >= REMEMBERED:
                                seen.clear()
                            seen.add(name)
                            new_names.append(name)
                            new_sizes.append(to - at)
                            payloads.append(part)
                        at = to
                    counts.append(at)
                    roots.append(merkle_root(leaves))
                    names += leaves
                    recipe.append(len(names))
                    fresh.append(len(new_names))
                widths = []
                for i, part in enumerate(payloads):
                    ids = np.frombuffer(part, dtype="<u4")
                    widths.append(2 if ids.max() < 65536 else 4)
                    payloads[i] = ids.astype(f"<u{widths[-1]}").tobytes()
                pairs = pa.StructArray.from_arrays([pa.array(names, pa.binary()), pa.array(sizes, pa.int32())], ["digest", "n_ids"])
                whole = pa.StructArray.from_arrays([pa.array(new_names, pa.binary()), pa.array(new_sizes, pa.int32()), pa.array(widths, pa.int32()), pa.array(payloads, pa.binary())], ["digest", "n_ids", "width", "payload"])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, 256), pa.array(counts, pa.int64()), pa.array(roots, pa.binary()), pa.ListArray.from_arrays(pa.array(recipe, pa.int32()), pairs), pa.ListArray.from_arrays(pa.array(fresh, pa.int32()), whole)], ["doc_id", "n_tokens", "root", "chunks", "fresh"])

    encoded = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(encode, f"doc_id {kind}, n_tokens long, root binary, chunks {RECIPE}, fresh array<struct<digest:binary,n_ids:int,width:int,payload:binary>>")
    staged = written(encoded, "encoded")

    def number(batches):
        file_no, row, start = TaskContext.get().partitionId(), 0, 0
        for batch in batches:
            n = batch.column(1).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), file_no, np.int32)), pa.array(np.arange(row, row + len(n), dtype=np.int64)), batch.column(0), batch.column(1), pa.array(start + np.cumsum(n) - n), *batch.columns[2:]], ["file_no", "row_no", "doc_id", "n_tokens", "start_in_file", "root", "chunks"])
            row, start = row + len(n), start + int(n.sum())

    ordered = staged.select("doc_id", "n_tokens", "root", "chunks").repartitionByRange(F.asc_nulls_first("doc_id"), "root").sortWithinPartitions(F.asc_nulls_first("doc_id"), "root")
    ordered.mapInArrow(number, f"file_no int, row_no long, doc_id {kind}, n_tokens long, start_in_file long, root binary, chunks {RECIPE}").write.parquet(f"{folder}/recipes")

    def once(batches):
        seen = set()
        for batch in batches:
            names = batch.column(0).to_pylist()
            keep = [not (x in seen or seen.add(x)) for x in names]
            yield batch.filter(pa.array(keep))

    fresh = staged.select(F.explode("fresh").alias("c")).select("c.digest", "c.n_ids", "c.width", "c.payload")
    fresh.repartition("digest").mapInArrow(once, fresh.schema).write.option("compression", "zstd").parquet(f"{folder}/chunks")

    recipes = spark.read.parquet(f"{folder}/recipes")

    # leaves of a file are hashed in blocks of rows, so that no task holds a whole file's roots as rows
    over = lambda order: F.unhex(F.sha2(F.concat_ws("", F.transform(F.sort_array(F.collect_list(F.struct(order, "root"))), lambda x: F.hex(x["root"]))), 256))
    by_block = recipes.groupBy("file_no", F.floor(F.col("row_no") / 4096).alias("block")).agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"), over("row_no").alias("root"))
    by_block.groupBy("file_no").agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"), over("block").alias("root")).write.parquet(f"{folder}/manifest")
    return open_store(spark, folder)


def open_store(spark: SparkSession, folder: str) -> Store:
    return Store(*(spark.read.parquet(f"{folder}/{x}") for x in ("chunks", "recipes", "manifest")), folder)


def read_documents(store: Store) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32, n_chunks, verified), from the files.

    Every stored chunk is read and its digest taken again; documents get their chunks' sums, which join to the sum of
    the whole, so that payloads are never shuffled.  ``verified`` says that all chunks are there and sound and the root holds.
    """

    def sums(batch: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for name, n, width, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            data = np.frombuffer(payload, dtype=f"<u{width}").astype("<u4").tobytes()
            out.append((zlib.crc32(data), digest(data) == name and len(data) == 4 * n))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _ in out], pa.int64()), pa.array([x for _, x in out])], ["digest", "crc", "sound"])

    stored = by_batch(store.chunks.select("digest", "n_ids", "width", "payload"), sums, "digest binary, crc long, sound boolean")
    parts = store.recipes.select("file_no", "row_no", F.posexplode("chunks").alias("pos", "c")).select("file_no", "row_no", "pos", "c.digest", "c.n_ids")
    found = parts.join(stored, "digest", "left")
    whole = found.groupBy("file_no", "row_no").agg(F.sort_array(F.collect_list(F.struct("pos", "n_ids", "crc", "sound", "digest"))).alias("parts"))

    def joined(batch: pa.RecordBatch) -> pa.RecordBatch:
        lists = batch.column(2)
        ends, flat = np.asarray(lists.offsets).tolist(), lists.values
        sizes, sums, good, names = (flat.field(x).to_pylist() for x in ("n_ids", "crc", "sound", "digest"))
        total, roots, sound = [], [], []
        for lo, hi in zip(ends, ends[1:]):
            value = 0
            for k in range(lo, hi):
                value = join_crc(value, sums[k] or 0, 4 * sizes[k])
            total.append(value)
            roots.append(merkle_root(names[lo:hi]))
            sound.append(all(good[lo:hi]))
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(total, pa.int64()), pa.array(roots, pa.binary()), pa.array(sound, pa.bool_()), pa.array(np.diff(ends), pa.int32())], ["file_no", "row_no", "ids_crc32", "made_root", "sound", "n_chunks"])

    made = by_batch(whole, joined, "file_no int, row_no long, ids_crc32 long, made_root binary, sound boolean, n_chunks int")
    offsets = store.manifest.select("file_no", F.coalesce(F.sum("n_tokens").over(Window.orderBy("file_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))  # one row a file
    kept = store.recipes.select("file_no", "row_no", "doc_id", "n_tokens", "start_in_file", "root")
    return kept.join(made, ["file_no", "row_no"], "left").join(offsets, "file_no").select(
        "doc_id", (F.col("before") + F.col("start_in_file")).alias("start"), "n_tokens", "ids_crc32", "n_chunks", (F.coalesce(F.col("sound"), F.lit(False)) & F.coalesce(F.col("made_root") == F.col("root"), F.lit(False))).alias("verified")
    )


def reconstruct(store: Store, where: Column | None = None) -> DataFrame:
    """(doc_id, ids) of the documents that ``where`` picks, put together from their chunks."""
    recipes = store.recipes if where is None else store.recipes.where(where)
    parts = recipes.select("file_no", "row_no", "doc_id", F.posexplode("chunks").alias("pos", "c")).select("file_no", "row_no", "doc_id", "pos", "c.digest")
    whole = parts.join(store.chunks.select("digest", "width", "payload"), "digest").groupBy("file_no", "row_no", "doc_id").agg(F.sort_array(F.collect_list(F.struct("pos", "width", "payload"))).alias("parts"))

    def join(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids = [np.concatenate([np.frombuffer(p["payload"], dtype=f"<u{p['width']}").astype(np.int32) for p in parts]) for parts in batch.column(1).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    kind = store.recipes.schema["doc_id"].dataType.simpleString()
    return by_batch(whole.select("doc_id", "parts"), join, f"doc_id {kind}, ids array<int>")
