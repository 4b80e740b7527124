"""Best-fit packing of token sequences by minimum bin slack.

Pieces of one length are interchangeable, so packing needs the histogram of lengths only: at most
``capacity`` counts, whatever the size of the corpus.  For each bin the longest piece left is the seed,
and a bitset subset-sum over the lengths left finds the fullest completion; the same bin is cut as often
as the counts allow.  Pieces then take places by their rank among the pieces of their length.
"""

from __future__ import annotations

from collections.abc import Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of, written
from wsample.llm.tokens import crc, encoder

#: Ranks within a length are taken in salted runs of about ``RUN_PIECES`` pieces, so that a length that most pieces share is no hot
#: key.  Runs grow with the table once there would be more than ``MOST_RUNS`` of them (and one a length).
RUN_PIECES, MOST_RUNS = 512, 50_000


def fullest(counts: Mapping[int, int], room: int) -> list[tuple[int, int]]:
    """(length, copies) of the fullest combination within ``room``, longer pieces first."""
    reach, trail, mask = 1, [], (1 << (room + 1)) - 1
    for length in sorted((x for x in counts if x <= room), reverse=True):
        before, left, step = reach, min(counts[length], room // length), 1
        while left:
            take = min(step, left)
            reach |= (reach << (take * length)) & mask
            left, step = left - take, step * 2
        trail.append((length, before))
        if reach >> room & 1:
            break
    total, out = reach.bit_length() - 1, []
    for length, before in reversed(trail):
        copies = 0
        while not before >> total & 1:  # fewest of the shorter ones
            total, copies = total - length, copies + 1
        if copies:
            out.append((length, copies))
    return out


def plan_bins(counts: Mapping[int, int], capacity: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """(times, [(length, copies)]) until every piece has a place."""
    left, plan = {k: n for k, n in counts.items() if n > 0}, []
    while left:
        seed = max(left)
        rest = dict(left)
        rest[seed] -= 1
        bin_ = {seed: 1}
        for length, copies in fullest({k: n for k, n in rest.items() if n}, capacity - seed):
            bin_[length] = bin_.get(length, 0) + copies
        times = min(left[k] // c for k, c in bin_.items())
        for k, c in bin_.items():
            left[k] -= times * c
            if not left[k]:
                del left[k]
        plan.append((times, sorted(bin_.items(), reverse=True)))
    return plan


def places(plan: list[tuple[int, list[tuple[int, int]]]]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """length -> (first rank, copies a bin, first sequence, offset in the bin), one entry for each bin shape that uses it."""
    rows: dict[int, list[tuple[int, int, int, int]]] = {}
    rank: dict[int, int] = {}
    sequence = 0
    for times, shape in plan:
        offset = 0
        for length, copies in shape:
            rows.setdefault(length, []).append((rank.get(length, 0), copies, sequence, offset))
            rank[length] = rank.get(length, 0) + times * copies
            offset += length * copies
        sequence += times
    return {k: tuple(np.array(x, dtype=np.int64) for x in zip(*v, strict=True)) for k, v in rows.items()}


def token_pieces(docs: DataFrame, path: str, *, capacity: int = 1024, end_id: int = 2, keep_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Token pieces of at most ``capacity`` of every whole text with its end id; only the first piece of a longer one may be short.

    A null text is empty and makes the end id alone.  Repeated rows make their own pieces.
    """

    def cut(batch: pa.RecordBatch) -> pa.RecordBatch:
        encode, end = encoder("byte", path), np.array([end_id], dtype="<u4").tobytes()
        row, piece, start, length, sums, ids = [], [], [], [], [], []
        for i, text in enumerate(batch.column(1).to_pylist()):
            data = encode(text) + end
            n = len(data) // 4
            at, k = 0, 0
            while at < n:
                size = (n - at) % capacity or capacity
                part = data[4 * at : 4 * (at + size)]
                row.append(i)
                piece.append(k)
                start.append(at)
                length.append(size)
                sums.append(crc(part))
                if keep_ids:
                    ids.append(np.frombuffer(part, dtype="<u4").astype(np.int32))
                at, k = at + size, k + 1
        columns = [batch.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(sums, pa.int64())]
        names = ["doc_id", "piece", "start", "length", "ids_crc32"]
        if keep_ids:
            columns.append(pa.array(ids, pa.list_(pa.int32())))
            names.append("ids")
        return pa.RecordBatch.from_arrays(columns, names)

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids
    return by_batch(docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")), cut, schema, size_by="text")


def runs_of(counts: Mapping[int, int]) -> dict[int, int]:
    """length -> salted runs; ``MOST_RUNS`` and one a length in all at most, whatever the counts."""
    size = max(RUN_PIECES, -(-sum(counts.values()) // MOST_RUNS))
    return {length: -(-n // size) for length, n in counts.items()}


def pack(pieces: DataFrame, *, capacity: int = 1024) -> DataFrame:
    """``pieces`` (doc_id, piece, start, length, ids_crc32, ...) with ``sequence_id`` and ``offset``.

    ``pieces`` is read more than once, so it should be a written table.  Equal lengths rank by ids, ties by content,
    and equal rows are interchangeable.  An empty table packs to an empty one.
    """
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``capacity`` rows
    if counts and max(counts) > capacity:
        raise ValueError("a piece is longer than a sequence")
    table = places(plan_bins(counts, capacity))
    many = pieces.sparkSession.createDataFrame([*runs_of(counts).items()], "length long, __runs long")  # at most ``capacity`` rows
    salt = F.pmod(F.xxhash64("doc_id", "piece", "start", "ids_crc32"), F.col("__runs")).cast("int")
    salted = pieces.join(F.broadcast(many), "length").withColumn("__run", salt).drop("__runs")
    before = Window.partitionBy("length").orderBy("__run").rowsBetween(Window.unboundedPreceding, -1)
    runs = salted.groupBy("length", "__run").agg(F.count("*").alias("__n")).select("length", "__run", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    order = Window.partitionBy("length", "__run").orderBy("doc_id", "piece", "start", "ids_crc32")
    # MOST_RUNS + capacity rows at most, however many pieces there are
    ranked = salted.withColumn("__k", F.row_number().over(order) - 1).join(F.broadcast(runs), ["length", "__run"]).withColumn("__rank", F.col("__k") + F.col("__before"))
    kept = [c for c in pieces.columns]
    ranked = ranked.select(*kept, "__rank")

    def place(batch: pa.RecordBatch) -> pa.RecordBatch:
        length = batch.column(kept.index("length")).to_numpy()
        rank = batch.column(len(kept)).to_numpy()
        sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
        for size in np.unique(length):
            at = np.flatnonzero(length == size)
            first, copies, base, place_ = table[int(size)]
            i = np.searchsorted(first, rank[at], side="right") - 1
            k = rank[at] - first[i]
            sequence[at] = base[i] + k // copies[i]
            offset[at] = place_[i] + k % copies[i] * size
        return pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(sequence), pa.array(offset)], [*kept, "sequence_id", "offset"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"
    return by_batch(ranked, place, schema)


def pack_documents(docs: DataFrame, path: str, *, capacity: int = 1024, end_id: int = 2, keep_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Whole texts to packed sequences: one row a piece."""
    pieces = written(token_pieces(docs, path, capacity=capacity, end_id=end_id, keep_ids=keep_ids, id_col=id_col, text_col=text_col), "pieces")
    return pack(pieces, capacity=capacity)
