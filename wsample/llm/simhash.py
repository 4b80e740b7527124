"""Near-duplicate documents by SimHash, found through the generalised pigeonhole principle.

A link between fingerprints of at most ``max_bits`` differing bits is found without comparing all pairs.
Bits are grouped into parts, correlated bits together; part i gets a threshold t_i (-1: not looked at)
with the thresholds adding to max_bits - parts + 1.  Two linked fingerprints then differ in at most t_i
bits of some part.  Thresholds come from dynamic programming over the expected candidates of each part,
which the bit counts of the whole corpus give.  Equal part values (and flips of up to t_i bits) meet in
buckets; every bucket is compared in blocks and leaves a spanning forest of its links, so that a group
of n copies costs n rows, not n squared.

Links by the Jaccard similarity of word shingles are sought among fingerprints first.  Texts that are similar enough also share
one of their rarest shingles, so then all that share one are compared, but for those that are joined already.  The pairs that
share a shingle grow faster than the texts, so texts are only fetched for those whose sketches (counts of distinct shingles by
leading hash bits, some fortieth of a text) leave room for the similarity; a sketch never rules out a similar pair.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, release, small_enough, text_of, written
from wsample.llm.graph import components
from wsample.llm.linehash import shingles_of

BITS = 64
#: Rows of a bucket that are compared at once; larger buckets are cut into blocks and compared block by block, each row
#: going to as many block pairs as its bucket has blocks, so large blocks shuffle less.
BLOCK = 16384
#: A shuffled row costs about as much as this many comparisons.
ROW_COST = 100
#: Texts in which common shingles are counted, about, and how many of those are kept.
SAMPLED, COMMON = 8_000, 1_000_000
#: Fewest buckets of a sketch, and distinct shingles a bucket, about.
BUCKETS, FILL = 64, 8
#: Up to so many keys are broadcast to fetch their texts; more are joined by a shuffle.
MOST_KEYS = 200_000
#: For products of similarities and counts, which are rounded.
SLACK = 1e-6
_LANES = np.uint64(0x0101010101010101)


def shingle_hashes(text: str, k: int) -> list[int]:
    """XXH64 (seed 42) of the k-word shingles of the text with A-Z lower-cased, repeats included; fewer words make one."""
    words = text.encode().lower().split()  # of bytes: ASCII letters and ASCII white space only
    if not words:
        return []
    data, ends = b" ".join(words), list(itertools.accumulate(len(w) + 1 for w in words))
    hash_ = xxhash.xxh64_intdigest
    if len(words) <= k:
        return [hash_(data, 42)]
    return [hash_(data[i : j - 1], 42) for i, j in zip([0, *ends], ends[k - 1 :], strict=False)]


def fingerprints_of(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Majority bits of each run of hashes; an empty run has fingerprint zero."""
    out = np.zeros(len(counts), np.uint64)
    full = np.flatnonzero(counts)
    if not len(full):
        return out
    n = counts[full]
    starts = np.cumsum(n) - n
    blocks = -(-n // 255)  # counters of eight bits
    block_of = np.cumsum(blocks) - blocks
    at = np.repeat(starts, blocks) + 255 * (np.arange(blocks.sum()) - np.repeat(block_of, blocks))
    for k in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(k)) & _LANES, at).view(np.uint8).reshape(-1, 8)
        sums = np.add.reduceat(lanes.astype(np.int64), block_of, axis=0)
        for byte in range(8):
            out[full] |= (2 * sums[:, byte] > n).astype(np.uint64) << np.uint64(8 * byte + k)
    return out


def sketch_of(hashes: np.ndarray) -> tuple[int, bytes]:
    """(distinct hashes, how many of them have each value of their leading bits); no counts, which rule nothing out, if a byte is too small for one."""
    distinct = np.unique(hashes)
    bits = max(BUCKETS.bit_length() - 1, (len(distinct) // FILL).bit_length())
    counts = np.bincount((distinct >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)
    return len(distinct), counts.astype(np.uint8).tobytes() if counts.max() <= 255 else b""


def apart(a: bytes, b: bytes) -> int:
    """A lower bound, from their sketches, of how many hashes two sets do not share."""
    if not a or not b:
        return 0
    x, y = np.frombuffer(a, np.uint8).astype(np.int64), np.frombuffer(b, np.uint8).astype(np.int64)
    few = min(len(x), len(y))
    return int(np.abs(x.reshape(few, -1).sum(axis=1) - y.reshape(few, -1).sum(axis=1)).sum())


def fingerprints(docs: DataFrame, *, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """(doc_id, fp, text_key): fingerprint as a long and a digest of the lower-cased words, and the text and its sketch (size, sketch) if asked for.  Null texts are empty."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        hashes, counts, keys = [], [], []
        for text in batch.column(1).to_pylist():
            found = shingle_hashes(text, shingle)
            hashes += found
            counts.append(len(found))
            keys.append(xxhash.xxh128_hexdigest(b" ".join(text.encode().lower().split())))
        all_, ends = np.array(hashes, np.uint64), np.cumsum(counts)
        more = []
        if with_text:
            sketches = [sketch_of(all_[end - n : end]) for n, end in zip(counts, ends.tolist(), strict=True)]
            more = [batch.column(1), pa.array([n for n, _ in sketches], pa.int32()), pa.array([x for _, x in sketches], pa.binary())]
        fp = fingerprints_of(all_, np.array(counts, np.int64))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp.view(np.int64)), pa.array(keys), *more], ["doc_id", "fp", "text_key", *(["text", "size", "sketch"] if with_text else [])])

    kind = docs.schema[id_col].dataType.simpleString()
    return by_batch(docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")), make, f"doc_id {kind}, fp long, text_key string" + ", text string, size int, sketch binary" * with_text, size_by="text")


@dataclass(frozen=True)
class Part:
    mask: int
    threshold: int


def bit_counts(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Rows, and how often each pair of bits is set together, over the whole table."""

    def count(batches):
        total, n = np.zeros((BITS, BITS), np.int64), 0
        for batch in batches:
            fp = batch.column(0).to_numpy().view(np.uint64)
            for lo in range(0, len(fp), 65536):
                bits = (fp[lo : lo + 65536, None] >> np.arange(BITS, dtype=np.uint64) & np.uint64(1)).astype(np.float32)
                total += np.rint(bits.T @ bits).astype(np.int64)
            n += len(fp)
        if n:
            i, j = np.indices((BITS, BITS)).reshape(2, -1)
            yield pa.RecordBatch.from_arrays([pa.array([*i, BITS], pa.int32()), pa.array([*j, BITS], pa.int32()), pa.array([*total.ravel(), n], pa.int64())], ["i", "j", "n"])

    both, n = np.zeros((BITS, BITS)), 0
    for i, j, k in fps.select("fp").mapInArrow(count, "i int, j int, n long").groupBy("i", "j").agg(F.sum("n")).collect():  # 64 * 64 + 1 rows
        if i == BITS:
            n = k
        else:
            both[i, j] = k
    return n, both


def grouped_bits(n: int, both: np.ndarray, parts: int) -> list[list[int]]:
    """Bits in ``parts`` groups of nearly equal width, the most correlated together."""
    p = np.diag(both) / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    like = np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
    np.fill_diagonal(like, 0)
    left, groups = set(range(BITS)), []
    for g in range(parts):
        width = -(-len(left) // (parts - g))
        seed = max(left, key=lambda i: (max((like[i, j] for j in left), default=0), -i))
        group = [seed]
        left.remove(seed)
        while len(group) < width:
            best = max(left, key=lambda i: (like[i, group].sum(), -i))
            group.append(best)
            left.remove(best)
        groups.append(sorted(group))
    return groups


def within(p: np.ndarray, most: int) -> np.ndarray:
    """Chance that two fingerprints differ in at most 0, 1, ... ``most`` of the bits, from the bits' shares."""
    differ = 2 * p * (1 - p)
    chance = np.zeros(len(p) + 1)
    chance[0] = 1
    for q in differ:
        chance[1:] = chance[1:] * (1 - q) + chance[:-1] * q
        chance[0] *= 1 - q
    return np.cumsum(chance)[: most + 1]


def allot(costs: list[list[float]], total: int) -> tuple[float, list[int]]:
    """Thresholds from -1 on, one a part, adding to ``total``, of least cost; costs[i][t + 1]."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for row in costs:
        then: dict[int, tuple[float, list[int]]] = {}
        for done, (cost, chosen) in best.items():
            for t, more in enumerate(row, start=-1):
                if done + t not in then or cost + more < then[done + t][0]:
                    then[done + t] = (cost + more, [*chosen, t])
        best = then
    return best[total]


def plan_parts(n: int, both: np.ndarray, max_bits: int, *, most_parts: int = 16) -> list[Part]:
    """Parts and thresholds of least expected cost over all numbers of parts."""
    p, plans = np.diag(both) / max(n, 1), []
    for m in range(1, min(max_bits + 2, most_parts) + 1):
        groups, costs = grouped_bits(n, both, m), []
        for g in groups:
            near = within(p[g], max_bits)
            rows = np.cumsum([_choose(len(g), d) for d in range(len(near))])
            costs.append([0.0, *(n * float(rows[t]) * (ROW_COST + n * float(near[t]) / 2) for t in range(len(near)))])
        cost, chosen = allot(costs, max_bits - m + 1)
        plans.append((cost, [Part(sum(1 << b for b in g), t) for g, t in zip(groups, chosen, strict=True) if t >= 0]))
    return min(plans, key=lambda x: x[0])[1]


def _choose(n: int, k: int) -> float:
    out = 1.0
    for i in range(k):
        out = out * (n - i) / (i + 1)
    return out


def flips(part: Part) -> np.ndarray:
    """Every way to flip up to the threshold of the part's bits."""
    bits = [1 << b for b in range(BITS) if part.mask >> b & 1]
    return np.array([sum(c) for t in range(part.threshold + 1) for c in itertools.combinations(bits, t)], np.uint64)


def forest(fp: np.ndarray, max_bits: int) -> list[tuple[int, int, int]]:
    """(i, j, bits) of a spanning forest of least bits over the links among ``fp``."""
    n = len(fp)
    linked = np.zeros(n, bool)
    for lo in range(0, n, 256):
        near = np.bitwise_count(fp[lo : lo + 256, None] ^ fp[None, :]) <= max_bits
        linked[lo : lo + 256] |= near.sum(axis=1) > 1
    at = np.flatnonzero(linked)
    if not len(at):
        return []
    f, out = fp[at], []
    far = np.uint8(255)
    nearest, parent, done = np.full(len(at), far), np.zeros(len(at), np.int64), np.zeros(len(at), bool)
    for _ in range(len(at)):
        open_ = np.where(done, 256, nearest.astype(np.int16))
        i = int(open_.argmin())
        if open_[i] <= max_bits:
            out.append((int(at[parent[i]]), int(at[i]), int(open_[i])))
        done[i] = True
        d = np.bitwise_count(f ^ f[i])
        closer = (d < nearest) & ~done
        nearest[closer], parent[closer] = d[closer], i
    return out


def links(nodes: DataFrame, max_bits: int) -> DataFrame:
    """(a, b, bits): a spanning forest of every bucket's links; ``nodes`` is a written table (key, fp), keys unique.

    All links of at most ``max_bits`` are joined by paths of such links.
    """
    n, both = bit_counts(nodes)
    kind = nodes.schema["key"].dataType.simpleString()
    parts = plan_parts(n, both, max_bits)
    table = [(i, np.uint64(p.mask), flips(p)) for i, p in enumerate(parts)]

    def emit(batches):
        for batch in batches:
            key, fp = batch.column(0), batch.column(1).to_numpy().view(np.uint64)
            for lo in range(0, len(fp), 4096):
                few = fp[lo : lo + 4096]
                for i, mask, turned in table:
                    for g in range(0, len(turned), 64):
                        value = ((few[:, None] ^ turned[None, g : g + 64]) & mask).ravel()
                        row = np.repeat(np.arange(lo, lo + len(few)), len(turned[g : g + 64]))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(value), i, np.int8)), pa.array(value.view(np.int64)), key.take(pa.array(row)), pa.array(fp[row].view(np.int64))], ["part", "value", "key", "fp"])

    rows = nodes.select("key", "fp").mapInArrow(emit, f"part byte, value long, key {kind}, fp long")
    large = rows.groupBy("part", "value").agg(F.count("*").alias("n")).where(F.col("n") > BLOCK).select("part", "value", F.ceil(F.col("n") / (BLOCK // 2)).cast("int").alias("blocks"))
    own = F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.struct(F.least(own, j).alias("bi"), F.greatest(own, j).alias("bj")))
    cut = rows.join(large, ["part", "value"], "left").withColumn("p", F.explode(F.when(F.col("blocks").isNull(), F.array(F.struct(F.lit(0).alias("bi"), F.lit(0).alias("bj")))).otherwise(pairs)))
    cut = cut.select("part", "value", F.col("p.bi").alias("bi"), F.col("p.bj").alias("bj"), "key", "fp")
    place = ["part", "value", "bi", "bj"]

    def compare(batches):
        """Runs of one bucket are whole, as the rows come sorted; the last run of a batch waits for the next."""
        rest = None
        for batch in itertools.chain(batches, [None]):
            if batch is not None:
                rest = batch if rest is None else pa.Table.from_batches([rest, batch]).combine_chunks().to_batches()[0]
            if rest is None or not rest.num_rows:
                continue
            named = [rest.column(c).to_numpy() for c in place]
            new = np.zeros(rest.num_rows, bool)
            for c in named:
                new[1:] |= c[1:] != c[:-1]
            starts = np.flatnonzero(new)
            ends = [*starts, rest.num_rows] if batch is None else [*starts]
            starts = [0, *starts][: len(ends)]
            fp, a, b, bits = rest.column("fp").to_numpy().view(np.uint64), [], [], []
            for lo, hi in zip(starts, ends, strict=True):
                if hi - lo > 1:
                    for i, j, d in forest(fp[lo:hi], max_bits):
                        a.append(lo + i)
                        b.append(lo + j)
                        bits.append(d)
            if a:
                key = rest.column("key")
                yield pa.RecordBatch.from_arrays([key.take(pa.array(a)), key.take(pa.array(b)), pa.array(bits, pa.int32())], ["a", "b", "bits"])
            rest = rest.slice(ends[-1]) if len(ends) else rest

    return cut.repartition(*place).sortWithinPartitions(*place).mapInArrow(compare, f"a {kind}, b {kind}, bits int")


def each_set(texts: pa.Array, shingle: int):
    """The distinct shingles of each text, sorted; texts are hashed some at a time."""
    lengths = pa.compute.binary_length(texts).to_numpy()
    cuts = np.flatnonzero(np.diff(np.cumsum(lengths) // 400_000, prepend=0))
    for lo, hi in itertools.pairwise(dict.fromkeys([0, *cuts.tolist(), len(texts)])):
        hashes, counts = shingles_of(texts.slice(lo, hi - lo), shingle)
        ends = np.cumsum(counts)
        for start, end in zip((ends - counts).tolist(), ends.tolist(), strict=True):
            yield np.unique(hashes[start:end])


def possible(pairs: DataFrame, texts: DataFrame, *, least: float, max_bits: int | None) -> DataFrame:
    """The pairs (a, b), once each, that may be similar for all that their sketches tell; texts: (key, fp, size, sketch).

    Of sets of x and y shingles of that Jaccard similarity, at most (1 - least) / (1 + least) * (x + y) are not shared.
    """
    side = lambda k: texts.select(F.col("key").alias(k), F.col("fp").alias(f"f{k}"), F.col("size").alias(f"n{k}"), F.col("sketch").alias(f"s{k}"))
    pairs = pairs.select("a", "b").distinct().join(side("a"), "a").join(side("b"), "b")
    if max_bits is not None:
        pairs = pairs.where(F.bit_count(F.col("fa").bitwiseXOR(F.col("fb"))) <= max_bits)
    share = (1 - least) / (1 + least)
    pairs = pairs.where(F.abs(F.col("na") - F.col("nb")) <= share * (F.col("na") + F.col("nb")) + SLACK)

    def keep(batch: pa.RecordBatch) -> pa.RecordBatch:
        room = share * (batch.column("na").to_numpy() + batch.column("nb").to_numpy()) + SLACK
        lost = np.array([apart(x, y) for x, y in zip(batch.column("sa").to_pylist(), batch.column("sb").to_pylist(), strict=True)])
        return batch.select(["a", "b"]).filter(pa.array(lost <= room))

    return by_batch(pairs.select("a", "b", "na", "nb", "sa", "sb"), keep, "a long, b long")


def similar(pairs: DataFrame, texts: DataFrame, *, shingle: int, least: float) -> DataFrame:
    """The pairs (a, b) whose texts share at least that part of their distinct word shingles (Jaccard); pairs is a written table, texts: (key, text)."""
    keys = pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct()
    some = texts.join(F.broadcast(keys) if small_enough(keys, MOST_KEYS) else keys, "key", "left_semi")  # MOST_KEYS rows
    side = lambda k: some.select(F.col("key").alias(k), F.col("text").alias(f"t{k}"))
    pairs = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b")

    def compare(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep = []
        for s, t in zip(each_set(batch.column(2), shingle), each_set(batch.column(3), shingle), strict=True):
            both = len(np.intersect1d(s, t, assume_unique=True))
            keep.append(both >= least * (len(s) + len(t) - both))
        return batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return by_batch(pairs.select("a", "b", "ta", "tb"), compare, "a long, b long", size_by="ta")


def common_shingles(texts: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes and counts of the shingles that several texts of a sample have; they only order shingles, so the sample costs no links."""
    share = max(1, texts.count() // SAMPLED)
    some = texts.where(F.pmod(F.xxhash64("key"), F.lit(share)) == 0).select("text")

    def spread(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.uint64), *each_set(batch.column(0), shingle)]).view(np.int64))], ["h"])

    counted = by_batch(some, spread, "h long", size_by="text").groupBy("h").agg(F.count("*").alias("n")).where("n > 1").orderBy(F.desc("n"), "h").limit(COMMON).toArrow()  # COMMON rows
    h, n = counted["h"].to_numpy().view(np.uint64), counted["n"].to_numpy()
    at = np.argsort(h)
    return h[at], n[at]


def prefixes(texts: DataFrame, shingle: int, least: float) -> DataFrame:
    """(token, key, size, pos): the rarest shingles of each text, so many that two texts of that similarity share one.

    Of the n distinct shingles of a text, another of Jaccard similarity ``least`` or more holds at least least * n; so both hold
    one of the first n - least * n + 1 in an order that is the same for all texts: by count in the sample, then by hash.
    """
    shared = texts.sparkSession.sparkContext.broadcast(common_shingles(texts, shingle))  # COMMON rows

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        common, counts = shared.value
        tokens, rows, sizes, places = [np.zeros(0, np.uint64)], [], [], [np.zeros(0, np.int32)]
        for h in each_set(batch.column(1), shingle):
            n = np.zeros(len(h), np.int64)
            if len(common) and len(h):
                at = np.minimum(np.searchsorted(common, h), len(common) - 1)
                n = np.where(common[at] == h, counts[at], 0)
            most = len(h) - math.ceil(least * len(h) - SLACK) + 1 if len(h) else 0
            tokens.append(h[np.argsort(n, kind="stable")[:most]])
            places.append(np.arange(len(tokens[-1]), dtype=np.int32))
            rows.append(len(tokens[-1]))
            sizes.append(len(h))
        row = np.repeat(np.arange(len(rows)), rows)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(tokens).view(np.int64)), batch.column(0).take(pa.array(row)), pa.array(np.array(sizes, np.int32)[row]), pa.array(np.concatenate(places))], ["token", "key", "size", "pos"])

    return by_batch(texts.select("key", "text"), make, "token long, key long, size int, pos int", size_by="text")


def runs(batches):
    """(batch, starts, ends) of the runs of equal tokens, of two rows or more; rows come sorted, and the last run of a batch waits for the next."""
    rest = None
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            rest = batch if rest is None or not rest.num_rows else pa.Table.from_batches([rest, batch]).combine_chunks().to_batches()[0]
        if rest is None or not rest.num_rows:
            continue
        token = rest.column("token").to_numpy()
        starts = np.flatnonzero(token[1:] != token[:-1]) + 1
        ends = np.append(starts, rest.num_rows) if batch is None else starts
        if len(ends):
            starts = np.append(0, starts)[: len(ends)]
            several = ends - starts > 1
            yield rest, starts[several], ends[several]
            rest = rest.slice(int(ends[-1]))


def repeated(rows: DataFrame) -> DataFrame:
    """The rows whose token others have."""

    def keep(batches):
        for batch, starts, ends in runs(batches):
            n = ends - starts
            yield batch.take(pa.array(np.arange(n.sum()) + np.repeat(starts - np.cumsum(n) + n, n)))

    return rows.repartition("token").sortWithinPartitions("token").mapInArrow(keep, rows.schema)


def met(key: np.ndarray, size: np.ndarray, pos: np.ndarray, root: np.ndarray, least: float, star: bool):
    """Pairs of different roots among the rows of one token that may be similar, some at once.

    The first token that two texts share leaves room for the overlap that they need; places that leave too little are no pair.
    """
    need, last = least / (1 + least), 1
    if not star:  # the root of most rows comes last, and is not paired with itself
        _, of, n = np.unique(root, return_inverse=True, return_counts=True)
        order = np.lexsort((of, n[of]))
        key, size, pos, root = key[order], size[order], pos[order], root[order]
        last = int(np.flatnonzero(root == root[-1])[0])
    for i in range(last):
        rest = slice(i + 1, None)
        room = np.minimum(size[i] - pos[i], size[rest] - pos[rest])
        ok = np.flatnonzero((room >= need * (float(size[i]) + size[rest]) - SLACK) & (root[rest] != root[i])) + i + 1
        if len(ok):
            yield np.minimum(key[i], key[ok]), np.maximum(key[i], key[ok])


def meeting(rows: DataFrame, least: float, *, star: bool) -> DataFrame:
    """(a, b), a < b: pairs of different roots that meet under a token and may be similar; rows: (token, key, size, pos, root).

    With ``star`` each token's rows are only paired with one of them.
    """

    def compare(batches):
        for batch, starts, ends in runs(batches):
            key, size, pos, root = (batch.column(c).to_numpy() for c in ("key", "size", "pos", "root"))
            a, b, made = [], [], 0
            for lo, hi in zip(starts, ends, strict=True):
                for x, y in met(key[lo:hi], size[lo:hi], pos[lo:hi], root[lo:hi], least, star):
                    a.append(x)
                    b.append(y)
                    made += len(x)
                    if made > 100_000:
                        yield _distinct(a, b)
                        a, b, made = [], [], 0
            if made:
                yield _distinct(a, b)

    kept = rows.select("token", "key", "size", "pos", "root").repartition("token").sortWithinPartitions("token", F.xxhash64("key"))
    return kept.mapInArrow(compare, "a long, b long").distinct()


def _distinct(a: list[np.ndarray], b: list[np.ndarray]) -> pa.RecordBatch:
    found = np.unique(np.stack([np.concatenate(a), np.concatenate(b)]), axis=1)
    return pa.RecordBatch.from_arrays([pa.array(found[0]), pa.array(found[1])], ["a", "b"])


def similar_roots(texts: DataFrame, *, shingle: int, least: float, max_bits: int | None, first_bits: int) -> DataFrame:
    """(node, root) over all links of :func:`similar`; ``texts`` is a written table (key, fp, text, size, sketch), keys unique longs.

    First what the fingerprints name within ``first_bits`` is compared by its texts.  That alone would lose links: similar texts
    may differ in more bits, and where many texts meet, a forest of few bits may pass by the pair that is similar.  So then
    every pair that shares a rare shingle is compared, but for those that links found before have joined: first each token's rows
    with one of them, so that a group of n copies costs n pairs, then what is still apart.
    """

    def near(pairs: DataFrame) -> DataFrame:
        left = written(possible(pairs, texts, least=least, max_bits=max_bits), "possible")
        kept = written(similar(left, texts, shingle=shingle, least=least), "links")
        release(left)
        return kept

    rooted = lambda found: rows.join(components(found, "a", "b").withColumnRenamed("node", "key"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    named = links(texts.select("key", "fp"), first_bits if max_bits is None else min(first_bits, max_bits))
    tried = written(named.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs")
    found = near(tried)
    rows = written(repeated(prefixes(texts, shingle, least)), "tokens")
    for star in (True, False):
        pairs = written(meeting(rooted(found), least, star=star).join(tried, ["a", "b"], "left_anti"), "pairs")
        found, tried = found.union(near(pairs)), tried.union(pairs)
    return components(found, "a", "b")


def near_duplicates(docs: DataFrame, *, shingle: int = 3, max_bits: int | None = 2, min_similarity: float | None = None, first_bits: int = 6, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fingerprint, component_id): component_id is the smallest id that links reach, a document's own included.

    Without ``min_similarity`` fingerprints link at ``max_bits`` or fewer differing bits; with it, texts link that also have that
    Jaccard similarity of their word shingles, and ``max_bits`` may be None: pairs within ``first_bits`` are tried first, and no
    others are left out.  Texts without words link with each other.  Null ids get a component but name none, so a group of null
    ids alone has a null component.  One row an input row.
    """
    by_text = min_similarity is not None
    made = written(fingerprints(docs, shingle=shingle, id_col=id_col, text_col=text_col, with_text=by_text), "fingerprints")
    name = "text_key" if by_text else "fp"
    whole = ["text", "size", "sketch"] if by_text else []
    classes = made.groupBy(F.col(name).alias("name")).agg(F.first("fp").alias("fp"), F.min("doc_id").alias("least"), *[F.first(c).alias(c) for c in whole])
    classes = written(classes.withColumn("key", F.monotonically_increasing_id() if by_text else F.col("fp")), "classes")
    if by_text:  # what holds texts goes as soon as nothing reads it any more
        texted, made = made, written(made.select("doc_id", "fp", "text_key"), "fingerprints")
        release(texted)
        roots = similar_roots(classes.select("key", "fp", *whole), shingle=shingle, least=min_similarity, max_bits=max_bits, first_bits=first_bits)
        texted, classes = classes, written(classes.select("name", "key", "least"), "classes")
        release(texted)
    else:
        roots = components(links(classes.select("key", "fp"), max_bits), "a", "b")
    rooted = classes.select("name", "key", "least").join(roots.withColumnRenamed("node", "key"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = rooted.join(least, "root").select(F.col("name").alias(name), "component_id")
    return made.select("doc_id", "fp", "text_key").join(named, name).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
