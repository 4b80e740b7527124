"""Headline queries and the growth experiments; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

import numpy as np
from pyspark.sql import SparkSession, Window
from pyspark.sql import functions as F

from wsample import samplers, workloads
from wsample.functions.randomness import keyed_hash
from wsample.operators import kernels, proportional, race

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
HEADLINE = (
    "race_orders_m50", "race_orders_m200", "race_lineitem_m200", "race_reservoir_orders", "race_jump_orders", "race_by_returnflag", "prop_distributed_orders", "prop_orders_m50_window", "prop_sequential_orders", "prop_jump_orders",
    "replacement_race_orders", "replacement_lookup", "bounded_parts_k2", "recency_race_events", "constant_rate_events", "poisson_orders", "inclusion_documents", "estimate_revenue", "ads_ranked_slots", "race_tumbling_events",
)
NS, MS = (5_000, 10_000, 20_000, 40_000, 60_000, 80_000, 100_000), (50, 150, 250, 350, 450, 550, 650, 750)
GRID_NS, RUNS = (1_000, 2_000, 3_000, 4_000, 5_000, 6_000), 100
VARIANTS = {"race": samplers.RaceSampler, "race_jump": samplers.RaceJumpSampler, "proportional": samplers.ProportionalSampler, "proportional_jump": samplers.ProportionalJumpSampler}


IDS = {"weight": "o_totalprice", "id_cols": ["o_orderkey"]}
PLANS = {
    "race": lambda df: race.race_sample(df, 200, **IDS),
    "race_jump": lambda df: kernels.race_kernel(df, 200, jump=True, **IDS),
    "proportional": lambda df: proportional.proportional_sample(df, 200, mode="distributed", **IDS),
    "proportional_jump": lambda df: proportional.proportional_sample(df, 200, mode="jump", **IDS),
}


def timed(f, runs: int = 3, of=min) -> float:
    took = []
    for _ in range(runs):
        start = time.perf_counter()
        f()
        took.append(time.perf_counter() - start)
    return round(float(of(took)), 6)


def noop(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def fit(x, y) -> dict:
    slope, base = np.polyfit(x, y, 1)
    r2 = 1 - ((np.array(y) - slope * np.array(x) - base) ** 2).sum() / max(((np.array(y) - np.mean(y)) ** 2).sum(), 1e-18)
    return {"slope": float(slope), "r2": round(float(r2), 4)}


def growth(weights: np.ndarray) -> dict:
    """Mean seconds, draws and insertions of each sampler over n at m = 200, and mean seconds of the race over a grid of n and m."""
    out: dict = {"n": {}, "m": {}}
    for name, kind in VARIANTS.items():
        rows = []
        for n in NS:
            w, made = weights[: min(n, len(weights))], []

            def run():
                s = kind(200, samplers.keyed_rng(7, len(made)))  # noqa: B023
                s.offer(range(len(w)), w)  # noqa: B023
                made.append((s.draws, s.insertions))  # noqa: B023

            rows.append({"n": len(w), "s": timed(run, RUNS, np.mean), "draws": float(np.mean([d for d, _ in made])), "insertions": float(np.mean([i for _, i in made])), "runs": RUNS})
        out["n"][name] = {"points": rows, "fit": fit([r["n"] for r in rows], [r["s"] for r in rows]), "rows_per_s": round(rows[-1]["n"] / rows[-1]["s"])}
    for n in GRID_NS:
        w = weights[:n]
        rows = [{"m": m, "s": timed(lambda m=m, w=w: samplers.RaceSampler(m, samplers.keyed_rng(7, m)).offer(range(len(w)), w), RUNS, np.mean)} for m in MS]
        out["m"][f"race_n{n}"] = {"points": rows, "fit": fit([r["m"] for r in rows], [r["s"] for r in rows]), "runs": RUNS}
    return out


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    queries: dict[str, float] = {}
    for name in HEADLINE:
        queries[name] = timed(lambda name=name: noop(workloads.QUERIES[name](spark, SF_DIR)), 2)
    orders = workloads.table(spark, SF_DIR, "orders").select("o_orderkey", "o_totalprice")
    weights = np.array([r[0] for r in orders.orderBy(keyed_hash(["o_orderkey"], seed=7)).select("o_totalprice").limit(max(NS)).collect()])
    grown = growth(weights)
    ranked = orders.withColumn("k", F.row_number().over(Window.orderBy(keyed_hash(["o_orderkey"], seed=7)))).cache()
    ranked.count()
    plans = {name: [{"n": n, "s": timed(lambda n=n, plan=plan: noop(plan(ranked.where(F.col("k") <= n))), 2)} for n in NS[::3]] for name, plan in PLANS.items()}
    print(json.dumps({"metric": "total_seconds_of_headline_queries", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": SF_DIR.rsplit("sf", 1)[-1], "growth": grown, "plans_over_n": plans}))


if __name__ == "__main__":
    main()
