"""Line deduplication by a deletion-neighbourhood join.

Two lines are near if one edit makes one the other: a word inserted, dropped or replaced where both have three words or
more; a character where both have fewer, and five characters or more (so an edit is at most a fifth of such a line).
Near lines share a variant with a unit deleted.  Two lines of n units that differ in unit p are equal without it, so they
meet under (variant, p, n); a line that lacks unit p of another is that other's variant, so they meet under the variant
itself.  Either way all that meet under a key link to its earliest line, and no pairs within a key are made.

A line makes variants only if another line has its first or its second half of units: the one edit leaves one of two
halves as it was, so nothing is lost, and units of the untouched half are not deleted.  The halves that lines share,
and the hashes of whole lines, go to the tasks as one bitmap; a bit that is set by chance costs variants, not results.

A line goes if an earlier line (by document id, then line number) equals it or is near it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, fitting, release, text_of, unused, written
from wsample.llm.linehash import LEAST_CHARS, WORDS, Lines, lines_of

#: The bitmap has this many bits a line, a power of two of them, and no more than the most (128 MB): beyond that it lets more through.
BITS_A_LINE, LEAST_BITS, MOST_BITS = 16, 2**20, 2**30
#: Lines of which a task remembers that it had them.
REMEMBERED = 2**20
#: Bytes of text that are hashed at once.
AT_ONCE = 400_000
#: A line that is more than this share of all occurrences is looked up in a broadcast table: of those there are at most 1 / HOT.
HOT = 1e-3


class Seen:
    """Which hashes a task has had lately: exact when it says so."""

    def __init__(self):
        self.kept = np.arange(REMEMBERED, dtype=np.uint64) + np.uint64(1)  # no hash has its place there

    def new(self, hashes: np.ndarray) -> np.ndarray:
        """Places of the hashes not had lately, each once."""
        _, at = np.unique(hashes, return_index=True)
        slot = (hashes[at] & np.uint64(REMEMBERED - 1)).astype(np.int64)
        at = at[self.kept[slot] != hashes[at]]
        self.kept[(hashes[at] & np.uint64(REMEMBERED - 1)).astype(np.int64)] = hashes[at]
        return np.sort(at)


def unit_list(line: str) -> tuple[str, list]:
    """What the edits of a line count: words as bytes, or the characters of its words joined by spaces."""
    words = line.encode().split()
    if len(words) >= WORDS:
        return "words", words
    return "characters", list(b" ".join(words).decode())


def within_one(a: list, b: list) -> bool:
    """Whether the edit distance is at most one."""
    if abs(len(a) - len(b)) > 1:
        return False
    same = 0
    while same < min(len(a), len(b)) and a[same] == b[same]:
        same += 1
    return a[same + (len(a) >= len(b)) :] == b[same + (len(b) >= len(a)) :]


def are_near(a: str, b: str) -> bool:
    (kind, x), (other, y) = unit_list(a), unit_list(b)
    return kind == other and (kind == "words" or min(len(x), len(y)) >= LEAST_CHARS) and within_one(x, y)


def _long(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def occurrences(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, line_no, whole, check) of every line that is not blank; whole and check are two hashes of its words."""

    def cut(batches):
        for batch in batches:
            for part in fitting(batch, "text", AT_ONCE):
                found = lines_of(part.column(1))
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(found.text)), pa.array(found.number.astype(np.int32)), _long(found.whole()), _long(found.check)], ["doc_id", "line_no", "whole", "check"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(cut, f"doc_id {kind}, line_no int, whole long, check long")


def _fresh(batches):
    """(lines, places of those that may have near ones and that the task has not had lately, their hashes)."""
    seen = Seen()
    for batch in batches:
        for part in fitting(batch, "text", AT_ONCE):
            found: Lines = lines_of(part.column(0))
            i = np.flatnonzero(found.comparable())
            whole = found.whole()
            i = i[seen.new(whole[i])]
            if len(i):
                yield found, i, whole[i]


def half_rows(docs: DataFrame, text_col: str) -> DataFrame:
    """(h, lo, hi) of the halves of lines, lo and hi being the line's hash, and of whole lines, where they differ."""

    def spread(batches):
        for found, i, whole in _fresh(batches):
            halves = found.halves(i)
            named = np.repeat(whole, 4)
            ends = np.zeros(len(whole), np.uint64)
            yield pa.RecordBatch.from_arrays([_long(np.concatenate([halves.ravel(), whole])), _long(np.concatenate([named, ends])), _long(np.concatenate([named, ends + np.uint64(1)]))], ["h", "lo", "hi"])

    return docs.select(text_of(text_col).alias("text")).mapInArrow(spread, "h long, lo long, hi long")


def bitmap(rows: DataFrame, bits: int) -> np.ndarray:
    """``bits`` bits, those of the keys set that several lines have; at most a word for each 64 bits comes to the driver."""
    shared = rows.groupBy("h").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).where("lo <> hi").select(F.pmod("h", F.lit(bits)).alias("bit"))
    words = shared.groupBy(F.shiftright("bit", 6).alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("bit", F.lit(64)).cast("int"))).alias("b")).toArrow()
    out = np.zeros(bits // 64, np.int64)
    out[words["w"].to_numpy()] = words["b"].to_numpy()
    return out.view(np.uint64)


def bits_for(lines: int) -> int:
    return min(MOST_BITS, max(LEAST_BITS, 1 << (BITS_A_LINE * lines - 1).bit_length() if lines else 0))


def variant_rows(docs: DataFrame, bits: np.ndarray, text_col: str) -> DataFrame:
    """(key, place, size, line, own, text) of the lines that share a half; the text in a line's own row only."""
    shared = docs.sparkSession.sparkContext.broadcast(bits)  # at most MOST_BITS bits

    def spread(batches):
        held = shared.value
        mask = np.uint64(64 * len(held) - 1)

        def told(h: np.ndarray) -> np.ndarray:
            at = h & mask
            return (held[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63)) & np.uint64(1)).astype(bool)

        for found, i, whole in _fresh(batches):
            halves = told(found.halves(i))
            some = halves.any(axis=1)
            i, whole, halves = i[some], whole[some], halves[some]
            for lo in range(0, len(i), 2000):
                cut = slice(lo, lo + 2000)
                yield _variants(found, i[cut], whole[cut], halves[cut], told)

    return docs.select(text_of(text_col).alias("text")).mapInArrow(spread, "key long, place int, size int, line long, own boolean, text string")


def _variants(found: Lines, i: np.ndarray, whole: np.ndarray, halves: np.ndarray, told) -> pa.RecordBatch:
    """Own rows, and what is left without a unit where a partner may need it: with the first half untouched the edit is behind it, else before.

    The rest is kept once with its place, for lines of as many units, and once as the shorter line that it may be.
    """
    n = found.size[i]
    of, place, rest = found.rests(i)
    size = n[of]
    replaced = np.flatnonzero(np.where(place >= size // 2, halves[of, 2], halves[of, 3]))
    dropped = np.flatnonzero(np.where(place >= (size - 1) // 2, halves[of, 0], halves[of, 1]))
    dropped = dropped[told(rest[dropped])]
    key = np.concatenate([whole, rest[replaced], rest[dropped]])
    at = np.concatenate([np.full(len(i), -1), place[replaced], np.full(len(dropped), -1)]).astype(np.int32)
    sizes = np.concatenate([n, size[replaced], size[dropped] - 1]).astype(np.int32)
    line = np.concatenate([whole, whole[of[replaced]], whole[of[dropped]]])
    own = np.arange(len(key)) < len(i)
    text = pa.concat_arrays([found.texts(i), pa.nulls(len(key) - len(i), pa.string())])
    return pa.RecordBatch.from_arrays([_long(key), pa.array(at), pa.array(sizes), _long(line), pa.array(own), text], ["key", "place", "size", "line", "own", "text"])


def near_lines(docs: DataFrame, lines: int, distinct: DataFrame, text_col: str) -> DataFrame:
    """(whole) of the lines with an earlier line near them, as a written table."""
    rows = written(variant_rows(docs, bitmap(half_rows(docs, text_col), bits_for(lines)), text_col), "variants")
    keys = ["key", "place", "size"]
    met = rows.groupBy(*keys).agg(F.min("line").alias("lo"), F.max("line").alias("hi")).where("lo <> hi").select(*keys)
    places = distinct.select(F.col("whole").alias("line"), "at")
    some = written(rows.select(*keys, "line", "own").join(met, keys, "left_semi").join(places, "line"), "meeting")
    who = F.struct("at", "line")
    best = some.groupBy(*keys).agg(F.min(F.when(F.col("own"), who)).alias("w"), F.min(F.when(~F.col("own"), who)).alias("v"))
    # a whole line and the lines that have it as a variant link to each other only; under a place all link
    other = F.when((F.col("place") >= 0) | F.col("own"), F.col("v")).otherwise(F.col("w"))
    linked = written(some.join(best, keys).select("line", "at", other.alias("o")).where("o.at < at").select("line", F.col("o.line").alias("other")).distinct(), "linked")
    wanted = linked.select(F.explode(F.array("line", "other")).alias("line")).distinct()
    texts = rows.where("own").select("line", "text").join(wanted, "line", "left_semi").dropDuplicates(["line"])
    pairs = linked.join(texts, "line").join(texts.select(F.col("line").alias("other"), F.col("text").alias("other_text")), "other").select("line", "text", "other_text")

    def verify(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep = [are_near(a, b) for a, b in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
        return batch.select(["line"]).filter(pa.array(keep, pa.bool_()))

    near = written(by_batch(pairs, verify, "line long").select(F.col("line").alias("whole")).distinct(), "near")
    release(rows, some, linked)
    return near


def removals(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, line_no, check, near) of every line occurrence that goes."""
    found = written(occurrences(docs, id_col, text_col), "lines")
    at, name = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "line_no"), ["whole", "check"]
    distinct = written(found.groupBy(*name).agg(F.min(at).alias("at"), F.count("*").alias("n")), "distinct")
    total = found.count()
    near = near_lines(docs, total, distinct, text_col).withColumn("near", F.lit(True))
    marked = distinct.join(near, "whole", "left").where("n > 1 or near").select(*name, "n", F.col("at").alias("kept"), F.coalesce("near", F.lit(False)).alias("near"))
    marked = written(marked, "marked")
    release(distinct, near)
    common = F.broadcast(marked.where(F.col("n") > max(1.0, HOT * total)).drop("n"))  # at most 1 / HOT rows
    rare = marked.where(F.col("n") <= max(1.0, HOT * total)).drop("n")
    every = found.join(common, name).unionByName(found.join(common, name, "left_anti").join(rare, name))
    return every.where(F.col("near") | (at > F.col("kept"))).select("doc_id", "line_no", "check", "near")


def dedup_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", keep_empty: bool = True) -> DataFrame:
    """``docs`` without the lines that go, and how many there were: n_lines, n_exact, n_near.

    Case and punctuation count, the white space between words does not.  Blank lines stay.  Null texts stay null.
    Rows of one id stand at one place: equal lines of theirs stay in each.  Null ids come last.  Columns of docs that are named
    like the three counts are replaced; all others stay, whatever their names.
    Without ``keep_empty`` a document that loses all its lines goes too; one that had none stays.
    """
    gone = removals(docs, id_col=id_col, text_col=text_col)
    own, listed = unused("__id", docs.columns), unused("__gone", docs.columns)
    lists = gone.groupBy(F.col("doc_id").alias(own)).agg(F.collect_list(F.struct("line_no", "check", "near")).alias(listed))
    joined = docs.join(lists, docs[id_col].eqNullSafe(F.col(own)), "left").drop(own)
    counts = ("n_lines", "n_exact", "n_near")
    names = [c for c in docs.columns if c not in counts]

    def apply(batches):
        for batch in batches:
            for part in fitting(batch, text_col, AT_ONCE):
                yield _without(part)

    def _without(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = batch.num_rows
        texts, gone = batch.column(text_col), batch.column(listed)
        found = lines_of(pa.compute.fill_null(texts, ""))
        full = np.bincount(found.text, minlength=rows)
        flat, of = gone.flatten(), np.repeat(np.arange(rows), pa.compute.list_value_length(gone).fill_null(0).to_numpy())
        number = flat.field(0).to_numpy(zero_copy_only=False).astype(np.int64)
        check, near = flat.field(1).to_numpy(zero_copy_only=False).view(np.uint64), flat.field(2).to_numpy(zero_copy_only=False).astype(bool)
        here, there = found.text << 32 | found.number, of << 32 | number
        at = np.minimum(np.searchsorted(here, there), max(len(here) - 1, 0))
        # rows of one id share their list: an entry is for the row that has this very line there
        true = np.flatnonzero((here[at] == there) & (found.check[at] == check)) if len(here) and len(there) else np.zeros(0, np.int64)
        _, once = np.unique(there[true], return_index=True)
        true = true[once]
        exact, close = (np.bincount(of[true[near[true] == x]], minlength=rows) for x in (False, True))
        out = texts.to_pylist()
        edges = np.searchsorted(of[true], np.arange(rows + 1))
        for r in np.flatnonzero(exact + close).tolist():
            drop = set(number[true[edges[r] : edges[r + 1]]].tolist())
            out[r] = "\n".join(line for k, line in enumerate(out[r].split("\n")) if k not in drop)
        columns = [pa.array(out, pa.string()) if c == text_col else batch.column(c) for c in names]
        return pa.RecordBatch.from_arrays([*columns, *(pa.array(t.astype(np.int32)) for t in (full, exact, close))], [*names, *counts])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name in names) + ", n_lines int, n_exact int, n_near int"
    done = joined.select(*names, listed).mapInArrow(apply, schema)
    return done if keep_empty else done.where("n_lines = 0 or n_exact + n_near < n_lines")
