"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.operators.inclusion import draw_inclusion, draw_inclusion_m2, inclusion_probabilities
from wsample.operators.prefix import running
from wsample.plans.shared import written
from wsample.samplers import keyed_rng


def time_runs(make: Callable[[], DataFrame], runs: int = 100) -> dict:
    """Mean, deviation and least wall time of running a plan to the end."""
    took = []
    for _ in range(runs):
        start = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - start)
    return {"runs": runs, "mean_s": float(np.mean(took)), "std_s": float(np.std(took)), "min_s": float(np.min(took))}


def linear_fit(points: DataFrame, x: str, y: str) -> dict:
    """Slope, intercept and r2 of y over x."""
    return points.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2")).first().asDict()


def inclusion_frequency(df: DataFrame, m: int, reps: int, *, weight: Column | str, id_cols: Sequence[str], seed: int = 0, tag: str = "rep", source: str = "xxhash") -> DataFrame:
    """(ids, hits): how often a draw-role sample of m has each item over ``reps`` samples, in one job; for small tables."""
    w = F.col(weight) if isinstance(weight, str) else weight
    many = df.select(*id_cols, w.cast("double").alias("__w")).crossJoin(df.sparkSession.range(reps).withColumnRenamed("id", "rep"))
    e = -F.ln(keyed_uniform([*id_cols, "rep"], seed=seed, tag=tag, source=source)) / F.col("__w")
    best = many.withColumn("r", F.row_number().over(Window.partitionBy("rep").orderBy(e, *id_cols)))
    return best.groupBy(*id_cols).agg(F.count(F.when(F.col("r") <= m, 1)).alias("hits"))


def law_frequencies(df: DataFrame, m: int, reps: int, *, weight: Column | str, id_cols: Sequence[str], kinds: dict[str, Callable], seed: int = 0, tasks: int = 16) -> DataFrame:
    """(sampler, item, hits): how often each of several samplers has each item over ``reps`` runs.

    ``kinds`` name functions of (weights, m, generator) that give the numbers of the sampled items.  Each run passes over all
    weights, which the tasks hold: 8 bytes an item.  A run's m hits are what is shuffled.
    """
    w = F.col(weight) if isinstance(weight, str) else weight
    rows = df.select(F.struct(*id_cols).alias("item"), w.cast("double").alias("w")).orderBy("item").toArrow()  # the table itself: an id and a weight an item
    weights = rows["w"].to_numpy()
    shared = df.sparkSession.sparkContext.broadcast(weights)

    def run(batches):
        for batch in batches:
            names, reps_of = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for name in dict.fromkeys(names):
                mine = [np.asarray(kinds[name](shared.value, m, keyed_rng(seed, rep)), np.int64) for n, rep in zip(names, reps_of, strict=True) if n == name]
                i, n = np.unique(np.concatenate(mine), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(i), pa.string()), pa.array(i), pa.array(n)], ["sampler", "i", "hits"])

    samplers = F.explode(F.array(*[F.lit(k) for k in kinds])).alias("sampler")
    each = df.sparkSession.range(reps, numPartitions=tasks).select(samplers, "id")
    hits = each.mapInArrow(run, "sampler string, i long, hits long").groupBy("sampler", "i").agg(F.sum("hits").alias("hits"))
    items = df.sparkSession.createDataFrame(pa.table({"i": pa.array(np.arange(len(weights))), "item": rows["item"].combine_chunks() if rows.num_rows else rows["item"]}))
    return items.select(samplers, "i", "item").join(hits, ["sampler", "i"], "left").select("sampler", "item", F.coalesce("hits", F.lit(0)).alias("hits"))


def beyond(hits: Column | str, runs: int, p: Column | str, *, sigmas: float = 4.5, slack: float = 3.0) -> Column:
    """Whether a count of hits is off its expectation by more than so many deviations and a few hits (for rare items)."""
    hits, p = (F.col(x) if isinstance(x, str) else x for x in (hits, p))
    return F.abs(hits - runs * p) > sigmas * F.sqrt(F.greatest(runs * p * (1 - p), F.lit(0.0))) + slack


def z_scores(hits: DataFrame, reps: int, chance: Column | str = "inclusion_prob") -> DataFrame:
    p = F.col(chance) if isinstance(chance, str) else chance
    return hits.withColumn("z", (F.col("hits") - reps * p) / F.sqrt(F.greatest(reps * p * (1 - p), F.lit(1e-12))))


#: Measures over all pairs of items are for small tables.
MOST_ITEMS = 20_000


def small(df: DataFrame) -> DataFrame:
    """The frame, if it has at most MOST_ITEMS rows."""
    if df.limit(MOST_ITEMS + 1).count() > MOST_ITEMS:
        raise ValueError(f"a measure over all pairs takes at most {MOST_ITEMS} items")
    return df


#: Rows of a bucket in :func:`dominated`, about, and the most buckets on a side.
BUCKET, MOST_BUCKETS = 8192, 256


def rising(x: np.ndarray, y: np.ndarray, point: np.ndarray) -> int:
    """Pairs of a point and a query (not ``point``) that is larger in x and in y, by merging."""
    order = np.lexsort((-y, x))  # among equal x, no later y is larger
    y, point = y[order], point[order]

    def count(lo: int, hi: int) -> tuple[int, np.ndarray, np.ndarray]:
        """The pairs among these rows, and the sorted y of their points and queries."""
        if hi - lo <= 64:
            v, p = y[lo:hi], point[lo:hi]
            found = int(np.count_nonzero(np.triu((v[:, None] < v[None, :]) & p[:, None] & ~p[None, :], 1)))
            return found, np.sort(v[p]), np.sort(v[~p])
        mid = (lo + hi) // 2
        n, a, b = count(lo, mid)
        k, c, d = count(mid, hi)
        return n + k + int(np.searchsorted(a, d, side="left").sum()), np.sort(np.concatenate([a, c]), kind="stable"), np.sort(np.concatenate([b, d]), kind="stable")

    return count(0, len(y))[0] if len(y) else 0


def dominated(points: DataFrame, queries: DataFrame) -> int:
    """How many pairs of a point and a query (i, y) have point.i < query.i and point.y < query.y; y is a double, rows of a null y have no pairs.

    Rows are dealt into ranges of i and of y.  Pairs of other ranges in both follow from the counts of rows in each cell; those of one
    range of i, and those of one range of y and different ranges of i, are counted by merging.  No pair is ever made.
    """
    rows = points.select("i", "y", F.lit(True).alias("point")).union(queries.select("i", "y", F.lit(False).alias("point"))).where("y is not null")
    n = rows.count()
    sides = min(MOST_BUCKETS, n // BUCKET + 1)
    rows = written(rows.repartitionByRange(sides, "i").withColumn("k", F.spark_partition_id()), "ranges")
    cuts = sorted(set(rows.approxQuantile("y", [j / sides for j in range(1, sides)], 1 / (4 * sides)))) if sides > 1 else []
    place = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col("y"))) if cuts else F.lit(0)
    x = F.dense_rank().over(Window.partitionBy("k").orderBy("i")).cast("long")
    rows = written(rows.withColumns({"x": x, "p": place}).drop("i"), "ranges")
    cells = rows.groupBy("k", "p").agg(F.count_if("point").alias("a"), F.count_if(~F.col("point")).alias("b")).collect()  # MOST_BUCKETS squared rows
    a, b = (np.zeros((sides + 1, len(cuts) + 2), np.int64) for _ in range(2))
    for r in cells:
        a[r["k"] + 1, r["p"] + 1], b[r["k"] + 1, r["p"] + 1] = r["a"], r["b"]
    before = a.cumsum(axis=0).cumsum(axis=1)
    found = sum(int(u) * int(v) for u, v in zip(before[:-1, :-1].ravel(), b[1:, 1:].ravel(), strict=True))

    def within(column: str):
        def count(table):
            return pa.table({"n": [rising(table[column].to_numpy(), table["y"].to_numpy(), table["point"].to_numpy())]})

        return count

    for by, column in (("k", "x"), ("p", "k")):
        both = rows.groupBy(by).agg(F.count_if("point").alias("a"), F.count_if(~F.col("point")).alias("b")).where("a > 0 and b > 0").select(by)
        some = rows.join(F.broadcast(both), by, "left_semi")  # MOST_BUCKETS rows
        found += some.groupBy(by).applyInArrow(within(column), "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return found


def pair_count(df: DataFrame, ids: Column) -> int:
    """How many pairs of rows have ids in rising order."""
    n, same = df.groupBy(ids.alias("i")).agg(F.count("*").cast("decimal(38,0)").alias("n")).agg(F.sum("n"), F.sum(F.col("n") * F.col("n"))).first()
    return (int(n) ** 2 - int(same)) // 2 if n is not None else 0


def pair_order_counts(df: DataFrame, *, weight: Column | str, id_cols: Sequence[str], seed: int = 0, tag: str = "race", source: str = "xxhash") -> DataFrame:
    """(n_pairs, n_ordered): pairs of items, and how many of them the first wins; sorts and merges, for tables of any size."""
    w = (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    keyed = df.select(F.struct(*id_cols).alias("i"), (-F.ln(keyed_uniform(list(id_cols), seed=seed, tag=tag, source=source)) / w).alias("y"))
    return df.sparkSession.createDataFrame([(pair_count(keyed, F.col("i")), dominated(keyed, keyed))], "n_pairs long, n_ordered long")


def pair_order_rate(df: DataFrame, *, weight: Column | str, id_cols: Sequence[str], **keys) -> DataFrame:
    """(n_pairs, n_ordered, expected): those counts and the law's sum of weight shares, which takes all pairs (for small tables)."""
    w = (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    each = small(df).select(F.struct(*id_cols).alias("i"), w.alias("w"))
    a, b = each.alias("a"), each.alias("b")
    expected = a.join(b, F.col("a.i") < F.col("b.i")).agg(F.sum(F.col("a.w") / (F.col("a.w") + F.col("b.w"))).alias("expected"))
    return pair_order_counts(df, weight=weight, id_cols=id_cols, **keys).crossJoin(expected)


def ratio_errors(df: DataFrame, *, weight: Column | str, chance: Column | str, id_cols: Sequence[str], tolerance: float = 1e-9) -> DataFrame:
    """(n_pairs, n_errors): pairs of items, and those whose chances are not in the ratio of their weights: |p1 w2 - p2 w1| > tolerance * w1.

    That is so where the first one's chance a unit of weight is off the second one's by more than tolerance / w2, so errors are
    counted as pairs below or above that span; no pair is made.
    """
    w, p = ((F.col(x) if isinstance(x, str) else x).cast("double") for x in (weight, chance))
    each = df.select(F.struct(*id_cols).alias("i"), (p / w).alias("q"), (F.lit(tolerance) / w).alias("span"))
    points = lambda sign: each.select("i", (sign * F.col("q")).alias("y"))
    bounds = lambda sign: each.select("i", (sign * F.col("q") - F.col("span")).alias("y"))
    wrong = sum(dominated(points(sign), bounds(sign)) for sign in (1, -1))
    return df.sparkSession.createDataFrame([(pair_count(each, F.col("i")), wrong)], "n_pairs long, n_errors long")


def role_gap_m2(df: DataFrame, *, weight: Column | str, id_cols: list[str]) -> DataFrame:
    """(n, max_gap, total_gap) between the two roles' chances at two draws."""
    incl = inclusion_probabilities(df, 2, weight=weight).select(*id_cols, "inclusion_prob")
    draw = draw_inclusion_m2(df, weight=weight, id_cols=id_cols).select(*id_cols, F.col("inclusion_prob").alias("draw_prob"))
    gap = F.abs(F.col("inclusion_prob") - F.col("draw_prob"))
    return incl.join(draw, id_cols).agg(F.count("*").alias("n"), F.max(gap).alias("max_gap"), F.sum(gap).alias("total_gap"))


def role_gap(df: DataFrame, m: int, *, weight: Column | str, id_cols: list[str], method: str) -> DataFrame:
    """(n, max_gap, total_gap) between the two roles' chances at m draws; ``method`` is that of the draw role."""
    incl = inclusion_probabilities(df, m, weight=weight).select(*id_cols, "inclusion_prob")
    draw = draw_inclusion(df, m, weight=weight, id_cols=id_cols, method=method).select(*id_cols, F.col("inclusion_prob").alias("draw_prob"))
    gap = F.abs(F.col("inclusion_prob") - F.col("draw_prob"))
    return incl.join(draw, id_cols).agg(F.count("*").alias("n"), F.max(gap).alias("max_gap"), F.sum(gap).alias("total_gap"))


def expected_insertions(df: DataFrame, m: int, *, weight: Column | str, order_by: Sequence[str]) -> DataFrame:
    """(n, expected): acceptances of the inclusion role over an order, the sum of min(1, m * weight / running weight)."""
    w = (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    sums = running(df.withColumn("__w", w), order_by, {"__run": F.col("__w")})
    return sums.agg(F.count("*").alias("n"), F.sum(F.least(F.lit(1.0), F.lit(m) * F.col("__w") / F.col("__run"))).alias("expected"))


def plan_cost(df: DataFrame) -> dict:
    """Exchanges, sorts, Python nodes, broadcasts and whole-stage spans of the physical plan, and the optimizer's bytes and rows."""
    stats = df._jdf.queryExecution().optimizedPlan().stats()
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda *names: sum(text.count(x) for x in names)
    return {"exchanges": count("Exchange "), "sorts": count("Sort ["), "python": count("InArrow", "InPandas", "PythonUDF"), "top_k": count("TakeOrderedAndProject"), "group_limits": count("WindowGroupLimit"), "broadcasts": count("BroadcastExchange"), "spans": text.count("WholeStageCodegen") or text.count("*("), "bytes": int(str(stats.sizeInBytes())), "rows": int(str(stats.rowCount().get())) if stats.rowCount().isDefined() else None, "text": text}



def prefix_check(batches: DataFrame, population: DataFrame, sample: Callable[[DataFrame], DataFrame], *, batch: str, order: str, ids: Sequence[str], last: dict[int, object]) -> DataFrame:
    """(batch, ok): whether the reservoir after each batch is the batch sample of everything up to it."""
    rows = []
    for b, upto in sorted(last.items()):
        want = {tuple(r) for r in sample(population.where(F.col(order) <= F.lit(upto))).select(*ids).collect()}
        got = {tuple(r) for r in batches.where(F.col(batch) == b).select(*ids).collect()}
        rows.append((b, want == got))
    return batches.sparkSession.createDataFrame(rows, "batch int, ok boolean")
