"""Inclusion chances: exact for the inclusion role, by four methods for the draw role."""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsample.functions.weights import positive_weight
from wsample.operators.prefix import running
from wsample.plans.shared import written

#: Rows whose draw-role chances one call works out.
CHUNK = 4096


def threshold(df: DataFrame, m: int, *, weight: Column | str, on_bad_weight: str = "error") -> tuple[float, int]:
    """(threshold, overweight items): an item's chance is min(1, weight / threshold).

    One total and the m heaviest weights settle it; there is no sort of the population.  Up to m items: 0 and their count.
    """
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    weights = good.select(w.alias("w"))
    n, total = weights.agg(F.count("*"), F.sum("w")).first()
    if n <= m:
        return 0.0, n
    heaviest = [r["w"] for r in weights.orderBy(F.desc("w")).limit(m).collect()]  # m rows
    rest, pinned = total, 0
    for x in heaviest:
        if (m - pinned) * x <= rest:
            break
        rest, pinned = rest - x, pinned + 1
    return rest / (m - pinned), pinned


def inclusion_probabilities(df: DataFrame, m: int, *, weight: Column | str, on_bad_weight: str = "error") -> DataFrame:
    """``df`` with inclusion_prob, adjusted_weight and is_overweight (relative weight strictly above its share)."""
    tau, _ = threshold(df, m, weight=weight, on_bad_weight=on_bad_weight)
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    chance = F.least(F.lit(1.0), w / F.lit(tau)) if tau else F.lit(1.0)
    return good.withColumns({"inclusion_prob": chance, "adjusted_weight": F.greatest(w, F.lit(tau)), "is_overweight": w > F.lit(tau)})


def draw_inclusion_m2(df: DataFrame, *, weight: Column | str, id_cols: list[str]) -> DataFrame:
    """Draw-role chances at two draws, in closed form: one aggregate."""
    good, w = positive_weight(df, weight)
    rows = good.select(*id_cols, w.alias("w"))
    total = rows.agg(F.sum("w").alias("total"))
    odds = rows.crossJoin(F.broadcast(total)).select(*id_cols, "w", "total", (F.col("w") / (F.col("total") - F.col("w"))).alias("odds"))
    over = odds.agg(F.sum("odds").alias("all_odds"))
    return odds.crossJoin(F.broadcast(over)).select(*id_cols, (F.col("w") / F.col("total") * (1 + F.col("all_odds") - F.col("odds"))).alias("inclusion_prob"))


def enumerate_draws(weights, m: int) -> np.ndarray:
    """Draw-role chances over all ordered samples; for a handful of items."""
    w, out = np.asarray(weights, float), np.zeros(len(weights))
    for order in itertools.permutations(range(len(w)), min(m, len(w))):
        left, p = w.sum(), 1.0
        for i in order:
            p, left = p * w[i] / left, left - w[i]
        out[list(order)] += p
    return out


def time_nodes(total: float, least: float, *, step: float = 0.2) -> tuple[np.ndarray, np.ndarray]:
    """Times and their weights: equal steps of log time, from where no item is done to where all are.

    The integrands are smooth in log time whatever the spread of the weights, and the rule's error falls exponentially in 1 / step.
    """
    t = np.exp(np.arange(-38 - np.log(total), 4 - np.log(least), step))
    return t, step * t


def _done(w: np.ndarray, t: np.ndarray, m: int, start: np.ndarray | None = None) -> np.ndarray:
    """Chances of 0 .. m - 1 done by each time, of the items and those that ``start`` counts."""
    count = np.zeros((m, len(t))) if start is None else start.copy()
    if start is None:
        count[0] = 1
    for early, late in zip(-np.expm1(-np.outer(w, t)), np.exp(-np.outer(w, t)), strict=True):
        count[1:] = count[1:] * late + count[:-1] * early
        count[0] *= late
    return count


def _joined(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The counts of two disjoint sets of items together."""
    out = np.zeros_like(a)
    for k in range(len(a)):
        out[k:] += a[k] * b[: len(a) - k]
    return out


def _around(counts: list[np.ndarray], start: np.ndarray) -> list[np.ndarray]:
    """For each of some sets, the count of all others and ``start``; sums of products of chances only, so nothing cancels."""
    after = [start]
    for c in reversed(counts[1:]):
        after.append(_joined(after[-1], c))
    out, before = [], None
    for c in counts:
        rest = after.pop()
        out.append(rest if before is None else _joined(before, rest))
        before = c if before is None else _joined(before, c)
    return out


def _chances(w: np.ndarray, t: np.ndarray, g: np.ndarray, others: np.ndarray, block: int = 128) -> np.ndarray:
    """Draw-role chances of the items, where ``others`` counts all items besides them."""
    m, out = len(others), np.empty(len(w))
    cuts = range(0, len(w), block)
    for lo, count in zip(cuts, _around([_done(w[i : i + block], t, m) for i in cuts], others), strict=True):
        some = w[lo : lo + block]
        early, late = -np.expm1(-np.outer(some, t)), np.exp(-np.outer(some, t))
        none = np.zeros_like(count)
        none[0] = 1
        after = [none]
        for e, q in zip(early[:0:-1], late[:0:-1], strict=True):
            c = after[-1] * q
            c[1:] += after[-1][:-1] * e
            after.append(c)
        for i in range(len(some)):  # the item is among the first m if fewer than m others are done before it
            fewer = (count * np.cumsum(after.pop(), axis=0)[::-1]).sum(axis=0)
            out[lo + i] = np.sum(g * some[i] * late[i] * fewer)
            new = count * late[i]
            new[1:] += count[:-1] * early[i]
            count = new
    return out


def quadrature_draws(weights, m: int) -> np.ndarray:
    """Draw-role chances by integrating over the time at which an item finishes with fewer than m others before it."""
    w = np.asarray(weights, float)
    if m >= len(w):
        return np.ones(len(w))
    if not m:
        return np.zeros(len(w))
    t, g = time_nodes(w.sum(), w.min())
    return _chances(w, t, g, _done(w[:0], t, m))


def quadrature_table(rows: DataFrame, m: int, *, id_cols: list[str]) -> DataFrame:
    """(ids, inclusion_prob) as :func:`quadrature_draws` gives them, for a table (ids, __w) of any size.

    Chunks of CHUNK rows each count their own items; the counts of all other chunks, m numbers a node and chunk, are broadcast.
    """
    n, total, least = rows.agg(F.count("*"), F.sum("__w"), F.min("__w")).first()
    if n <= m or not m:
        return rows.select(*id_cols, F.lit(float(m > 0)).alias("inclusion_prob"))
    t, g = time_nodes(total, least)
    rows = written(rows.withColumn("__chunk", F.floor(F.monotonically_increasing_id() / F.lit(CHUNK))), "weights")

    def count(key, table):
        return pa.table({"chunk": [key[0].as_py()], "counts": pa.array([_done(table["__w"].to_numpy(), t, m).tobytes()], pa.binary())})

    found = rows.groupBy("__chunk").applyInArrow(count, "chunk long, counts binary").orderBy("chunk").collect()  # a row a chunk
    counts = [np.frombuffer(r["counts"]).reshape(m, len(t)) for r in found]
    others = rows.sparkSession.sparkContext.broadcast(dict(zip([r["chunk"] for r in found], _around(counts, _done(np.empty(0), t, m)), strict=True)))  # a row a chunk

    def chances(key, table):
        p = _chances(table["__w"].to_numpy(), t, g, others.value[key[0].as_py()])
        return table.select(id_cols).append_column("inclusion_prob", pa.array(p))

    schema = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in id_cols) + ", inclusion_prob double"
    return rows.groupBy("__chunk").applyInArrow(chances, schema)


def large_n_time(df: DataFrame, m: int, *, weight: Column | str, bins: int = 512) -> float:
    """Time by which m items have finished on average, from a histogram of log weights: one aggregate of ``bins`` rows."""
    good, w = positive_weight(df, weight)
    span = good.agg(F.min(w), F.max(w)).first()
    if span[0] is None:
        return float("inf")
    lo, hi = np.log(span[0]), np.log(span[1])
    step = max((hi - lo) / bins, 1e-12)
    table = good.groupBy(F.floor((F.log(w) - F.lit(lo)) / F.lit(step)).alias("b")).agg(F.count("*").alias("n"), F.sum(w).alias("s")).collect()
    n = np.array([r["n"] for r in table], float)
    mean = np.array([r["s"] for r in table]) / n
    if m >= n.sum():
        return float("inf")
    a, b = 0.0, 1.0
    while (n * -np.expm1(-mean * b)).sum() < m:
        b *= 2
    for _ in range(200):
        t = (a + b) / 2
        a, b = (t, b) if (n * -np.expm1(-mean * t)).sum() < m else (a, t)
    return (a + b) / 2


def draw_inclusion(df: DataFrame, m: int, *, weight: Column | str, id_cols: list[str], method: str = "large_n") -> DataFrame:
    """(ids, inclusion_prob) of the draw role: ``m2`` closed form, ``large_n`` in the limit, ``quadrature`` of any table, or ``enumerate`` for small ones (at most 5,000 rows)."""
    if method == "m2":
        if m != 2:
            raise ValueError("the closed form is for two draws")
        return draw_inclusion_m2(df, weight=weight, id_cols=id_cols)
    good, w = positive_weight(df, weight)
    if method == "large_n":
        t = large_n_time(df, m, weight=weight)
        return good.select(*id_cols, (F.lit(1.0) if t == float("inf") else -F.expm1(-w * F.lit(t))).alias("inclusion_prob"))
    if method == "quadrature":
        return quadrature_table(good.select(*id_cols, w.alias("__w")), m, id_cols=id_cols)
    if method != "enumerate":
        raise KeyError(method)
    rows = good.select(*id_cols, w.alias("w")).orderBy(*id_cols).limit(5001).collect()
    if len(rows) > 5000:
        raise ValueError("too many rows for an exact evaluation")
    p = enumerate_draws([r["w"] for r in rows], m)
    made = [(*[r[c] for c in id_cols], float(x)) for r, x in zip(rows, p, strict=True)]
    schema = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in id_cols) + ", inclusion_prob double"
    return df.sparkSession.createDataFrame(made, schema)


def heavy_count(heaviest: list[float], rest: float, m: int) -> int:
    """How many of the heaviest m weights, in falling order, are overweight; ``rest`` is the total of all."""
    for pinned, x in enumerate(heaviest):
        if (m - pinned) * x <= rest:
            return pinned
        rest -= x
    return len(heaviest)


def overweight_trace(df: DataFrame, m: int, ks: list[int], *, weight: Column | str, order: list[str]) -> DataFrame:
    """(k, n_overweight): items overweight among the first k, for each given prefix.

    The rows between two neighbouring prefixes give one total and their m heaviest weights, by aggregates; the prefixes then
    follow from len(ks) totals and m * len(ks) weights.  No task sees the table, and no row is looked at for each prefix.
    """
    good, w = positive_weight(df, weight)
    edges = sorted(set(ks))
    numbered = running(good.select(*order, w.alias("__w")), order, {}, number="__i").where(F.col("__i") <= F.lit(edges[-1] if edges else 0))
    block = F.lit(0)
    for k in edges:
        block = block + (F.col("__i") > F.lit(k)).cast("int")
    rows = numbered.select(block.alias("b"), "__w")
    totals = {r["b"]: r["t"] for r in rows.groupBy("b").agg(F.sum("__w").alias("t")).collect()}  # a row a prefix
    ranked = rows.withColumn("r", F.row_number().over(Window.partitionBy("b").orderBy(F.desc("__w"))))
    heavy: dict[int, list[float]] = {}
    for r in ranked.where(F.col("r") <= m).select("b", "__w").collect():  # m rows a prefix
        heavy.setdefault(r["b"], []).append(r["__w"])
    made, top, total = [], [], 0.0
    for b, k in enumerate(edges):
        top, total = sorted([*top, *heavy.get(b, [])], reverse=True)[:m], total + totals.get(b, 0.0)
        made.append((k, heavy_count(top, total, m)))
    return good.sparkSession.createDataFrame(made, "k int, n_overweight int")
