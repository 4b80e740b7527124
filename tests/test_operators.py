"""Plans, bad input, streams, sources and estimates."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.operators import baselines, bounded, estimate, inclusion, kernels, measures, prefix, proportional, race, replacement, select
from wsample.sources import files, population
from wsample.streaming import reservoir


def items(spark, w):
    return spark.createDataFrame([(i, float(x) if x is not None else None) for i, x in enumerate(w)], "item int, w double")


def orders(spark, sf):
    return spark.read.parquet(f"{sf}/orders.parquet")


def test_plans(spark, sf):
    cost = measures.plan_cost(race.race_sample(orders(spark, sf), 50, weight="o_totalprice", id_cols=["o_orderkey"]))
    assert cost["top_k"] >= 1 and not cost["python"]
    grouped = measures.plan_cost(race.race_by_group(orders(spark, sf), 5, ["o_orderstatus"], weight="o_totalprice", id_cols=["o_orderkey"]))
    assert grouped["group_limits"] >= 2
    slots = bounded.slot_candidates(orders(spark, sf), 5, weight="o_totalprice", id_cols=["o_orderkey"], k=1, seed=1, tag="b", source="xxhash", on_bad_weight="error")
    assert measures.plan_cost(slots)["group_limits"] >= 2


def test_scan_reads_what_it_needs(spark, sf):
    text = measures.plan_cost(race.race_sample(orders(spark, sf), 50, weight="o_totalprice", id_cols=["o_orderkey"]).select("o_orderkey"))["text"]
    assert "o_orderpriority" not in text


@pytest.mark.parametrize("source", ["md5", "xxhash", "rand"])
def test_uniforms(spark, source):
    got = spark.range(5000).select(keyed_uniform(["id"], source=source).alias("u")).agg(F.min("u"), F.max("u"), F.avg("u"), F.stddev("u")).first()
    assert 0 < got[0] and got[1] < 1 and abs(got[2] - 0.5) < 0.02 and abs(got[3] - 12**-0.5) < 0.01
    with pytest.raises(ValueError):
        keyed_uniform(["id"], source="dice")


def test_bad_weights(spark):
    df = items(spark, [None, float("nan"), 0, -1, float("inf"), 2])
    for sample in (race.race_sample, proportional.proportional_sample):
        assert [r.item for r in sample(df, 3, weight="w", id_cols=["item"], on_bad_weight="drop").collect()] == [5]
        with pytest.raises(Exception, match="positive real"):
            sample(df, 3, weight="w", id_cols=["item"]).collect()
    with pytest.raises(ValueError):
        race.race_sample(df, 3, weight="w", id_cols=["item"], on_bad_weight="ignore")


def test_short_empty_and_extreme(spark):
    df = items(spark, [1, 2])
    assert race.race_sample(df, 5, weight="w", id_cols=["item"]).count() == 2
    with pytest.raises(ValueError):
        race.race_sample(df, 5, weight="w", id_cols=["item"], on_short="error")
    with pytest.raises(ValueError):
        race.race_sample(df, -1, weight="w", id_cols=["item"])
    assert race.race_sample(df, 0, weight="w", id_cols=["item"]).count() == 0
    none = df.limit(0)
    for f in (lambda d: race.race_sample(d, 3, weight="w", id_cols=["item"]), lambda d: proportional.proportional_sample(d, 3, weight="w", id_cols=["item"]), lambda d: replacement.replacement_sample(d, 3, weight="w", id_cols=["item"]), lambda d: replacement.replacement_sample(d, 99, weight="w", id_cols=["item"]), lambda d: bounded.bounded_sample(d, 3, weight="w", id_cols=["item"]), lambda d: kernels.race_kernel(d, 3, weight="w", id_cols=["item"])):
        assert f(none).count() == 0
    wide = items(spark, [1e-300, 1, 1e300])
    keyed = race.with_race_key(wide, weight="w", id_cols=["item"], form="gumbel").collect()
    assert np.isfinite([r.race_key for r in keyed]).all()
    assert [r.item for r in race.race_sample(wide, 3, weight="w", id_cols=["item"]).orderBy("position").collect()] == [2, 1, 0]


def test_big_m_is_the_same_sample(spark, sf, monkeypatch):
    want = {(r.o_orderkey, r.position) for r in race.race_sample(orders(spark, sf), 400, weight="o_totalprice", id_cols=["o_orderkey"]).collect()}
    monkeypatch.setattr(race, "BIG_M", 100)
    assert {(r.o_orderkey, r.position) for r in race.race_sample(orders(spark, sf), 400, weight="o_totalprice", id_cols=["o_orderkey"]).collect()} == want


def test_selector(spark, sf):
    df = orders(spark, sf)
    for kw in ({}, {"role": "inclusion"}, {"replacement": "full"}, {"replacement": 2}, {"method": "reservoir"}, {"method": "jump"}, {"role": "inclusion", "method": "sequential"}):
        assert select.weighted_sample(df, 10, weight="o_totalprice", id_cols=["o_orderkey"], **kw).count() == 10
    for kw in ({"role": "both"}, {"replacement": "some"}, {"role": "inclusion", "replacement": 2}):
        with pytest.raises(ValueError):
            select.weighted_sample(df, 10, weight="o_totalprice", id_cols=["o_orderkey"], **kw)


def test_prefix_sums_over_partitions(spark):
    df = spark.range(1000).repartition(7)
    got = prefix.running(df, ["id"], {"s": F.col("id")}, largest={"top": F.col("id")}, number="k").collect()
    assert all(r.s == r.id * (r.id + 1) // 2 and r.top == r.id and r.k == r.id + 1 for r in got) and len(got) == 1000


def test_prefix_sums_with_a_wide_payload(spark, sf):
    """Every row, a number for each, and the total, whatever the partitions; neighbours' shares meet at one number."""
    rows = spark.read.parquet(f"{sf.replace('0.001', '0.1')}/lineitem.parquet").limit(210_000).withColumn("id", F.monotonically_increasing_id()).withColumn("extra", F.repeat(F.lit("payload "), 9)).cache()
    n, total = rows.agg(F.count("*"), F.sum("l_extendedprice")).first()
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for parts in ("4", "200"):
            spark.conf.set("spark.sql.shuffle.partitions", parts)
            got = prefix.running(rows, [F.col("l_extendedprice").desc(), F.col("id")], {"s": F.col("l_extendedprice"), "q": F.col("l_linenumber")}, largest={"top": F.col("l_quantity")}, number="k", lower=True).cache()
            r = got.agg(F.count("*"), F.countDistinct("k"), F.max("k"), F.max("s"), F.max("top"), F.max("q"), F.min("s_lower")).first()
            want = rows.agg(F.max("l_quantity"), F.sum("l_linenumber")).first()
            assert r[:3] == (n, n, n) and r[3] == pytest.approx(total) and r[4] == want[0] and r[5] == want[1] and r[6] == 0
            nxt = got.select((F.col("k") - 1).alias("k"), F.col("s_lower").alias("from"))
            assert got.join(nxt, "k").where("s <> `from`").count() == 0
            assert set(rows.columns) <= set(got.columns)
            assert race.big_top_m(race.with_race_key(rows.select("id", "l_extendedprice"), weight="l_extendedprice", id_cols=["id"]), 70_000, ["id"]).agg(F.count("*"), F.max("position")).first()[:] == (70_000, 70_000)
            got.unpersist()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        rows.unpersist()


def test_large_samples_of_strata(spark, sf):
    """Above Spark's own rank cut every task cuts its strata; the sample is that of the plain ranks."""
    rows = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/lineitem.parquet").withColumn("id", F.monotonically_increasing_id()).repartition(5, "id")
    got = race.race_by_group(rows, 1500, ["l_returnflag"], weight="l_quantity", id_cols=["id"])
    keyed = race.with_race_key(rows, weight="l_quantity", id_cols=["id"])
    cut = race.surviving(keyed, 1500, ["l_returnflag"])
    assert cut.count() < rows.count() / 2
    want = {}
    for r in keyed.select("l_returnflag", "id", race.KEY).collect():
        want.setdefault(r.l_returnflag, []).append((r[race.KEY], r.id))
    assert {(r.l_returnflag, r.id, r.position) for r in got.collect()} == {(g, i, k) for g, v in want.items() for k, (_, i) in enumerate(sorted(v)[:1500], 1)}


def test_first_items_hold_slots(spark):
    """Two items of weights 100 and 1: the first has its share of the slots, by every method."""
    df = items(spark, [100, 1])
    for method in ("race_jump", "proportional_jump", "lookup", "race", "proportional"):
        m = 400 if method in ("race", "proportional") else 3000
        held = replacement.replacement_sample(df, m, weight="w", id_cols=["item"], method=method, seed=3).groupBy("item").count().collect()
        n = {r.item: r["count"] for r in held}
        assert n[0] + n.get(1, 0) == m and abs(n.get(1, 0) - m / 101) < 4.5 * (m / 101) ** 0.5 + 1, (method, n)


def test_empty_tables(spark):
    none = items(spark, [1]).limit(0)
    assert baselines.systematic_sample(none.withColumn("c", F.lit(1)), 3, units=F.col("c"), id_cols=["item"]).count() == 0
    assert baselines.sequential_draw(none, 2, weight="w", id_cols=["item"]).count() == 0
    assert inclusion.draw_inclusion(none, 3, weight="w", id_cols=["item"]).count() == 0
    assert replacement.single_slot_jump(none, weight="w", id_cols=["item"]).count() == 0
    assert proportional.by_group(none, 2, ["item"], weight="w", id_cols=["item"]).count() == 0
    for method in ("race_jump", "proportional_jump", "lookup", "proportional"):
        assert replacement.replacement_sample(none, 5, weight="w", id_cols=["item"], method=method).count() == 0


def test_trace_of_pins(spark):
    """An item is overweight, and released by later ones."""
    got = {r.k: r.n_overweight for r in inclusion.overweight_trace(items(spark, [1, 1, 1, 4, 3, 9]), 2, [3, 4, 5, 6], weight="w", order=["item"]).collect()}
    assert got == {3: 0, 4: 1, 5: 0, 6: 0}


def test_distributed_inclusion_frequencies(spark):
    w, m, n = [8.0, 1.0, 1.0, 1.0, 9.0, 2.0, 3.0, 3.0], 3, 60
    df = items(spark, w).repartition(4, "item").cache()
    p = {r.item: r.inclusion_prob for r in inclusion.inclusion_probabilities(df, m, weight="w").collect()}
    hits = dict.fromkeys(range(8), 0)
    for seed in range(n):
        got = proportional.proportional_sample(df, m, weight="w", id_cols=["item"], seed=seed).collect()
        assert len(got) == m
        for r in got:
            hits[r.item] += 1
    assert all(abs(hits[i] - n * p[i]) < 4.5 * (n * p[i] * (1 - p[i])) ** 0.5 + 1e-9 for i in p)


def test_inclusion_methods_agree(spark, sf):
    df = orders(spark, sf).limit(300)
    f = lambda method, m=2: {r.o_orderkey: r.inclusion_prob for r in inclusion.draw_inclusion(df, m, weight="o_totalprice", id_cols=["o_orderkey"], method=method).collect()}
    a, b, c = f("m2"), f("quadrature"), f("large_n", 30)
    assert max(abs(a[k] - b[k]) for k in a) < 1e-6
    d = f("quadrature", 30)
    assert max(abs(c[k] - d[k]) for k in c) < 0.01 and sum(d.values()) == pytest.approx(30, rel=1e-4)


def test_role_gap_falls_with_n(spark, sf):
    df = orders(spark, sf)
    gaps = [measures.role_gap_m2(df.orderBy("o_orderkey").limit(n), weight="o_totalprice", id_cols=["o_orderkey"]).first().max_gap for n in (20, 150, 1500)]
    assert gaps[0] > gaps[1] > gaps[2]


def test_estimates_cover_the_truth(spark, sf):
    df = orders(spark, sf)
    truth = df.agg(F.sum("o_totalprice")).first()[0]
    good = []
    for seed in range(12):
        s = estimate.draw_sample_with_chances(df, 100, weight="o_totalprice", id_cols=["o_orderkey"], seed=seed)
        r = estimate.estimate_total(s, F.col("o_totalprice")).first()
        good.append(abs(r.estimate - truth) < 4 * r.std_error + 0.25 * truth)
    assert all(good)


def test_frequencies_and_z(spark):
    df = items(spark, [1, 1, 1, 2])
    hits = measures.inclusion_frequency(df, 2, 3000, weight="w", id_cols=["item"])
    p = inclusion.draw_inclusion(df, 2, weight="w", id_cols=["item"], method="enumerate")
    assert all(abs(r.z) < 4.5 for r in measures.z_scores(hits.join(p, "item"), 3000).collect())


def test_baseline_sizes(spark, sf):
    df = orders(spark, sf).withColumn("cents", F.round(F.col("o_totalprice") * 100).cast("long"))
    for m in (1, 20, 77):
        assert baselines.systematic_sample(df, m, units=F.col("cents"), id_cols=["o_orderkey"]).count() == m
    assert baselines.uniform_sample(df, 9, id_cols=["o_orderkey"]).count() == 9


def test_stream_restart_duplicates_and_prefixes(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").where("value > 0").orderBy("ts", "event_id")
    rows = events.collect()
    cut = [rows[i * 100 : (i + 1) * 100] for i in range(5)]
    folder = str(tmp_path / "in")
    state = reservoir.StreamingRace(spark, 20, weight="value", id_cols=["event_id"], folder=str(tmp_path / "state"))

    def drain():
        stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
        stream.writeStream.foreachBatch(state.foreach).option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start().awaitTermination()

    for part in cut[:3]:
        spark.createDataFrame(part, events.schema).coalesce(1).write.mode("append").parquet(folder)
    drain()
    spark.createDataFrame(cut[1], events.schema).coalesce(1).write.mode("append").parquet(folder)  # again
    for part in cut[3:]:
        spark.createDataFrame(part, events.schema).coalesce(1).write.mode("append").parquet(folder)
    drain()
    whole = spark.createDataFrame([r for c in cut for r in c], events.schema)
    want = {(r.event_id, r.position) for r in race.race_sample(whole, 20, weight="value", id_cols=["event_id"]).collect()}
    assert {(r.event_id, r.position) for r in state.sample().collect()} == want
    assert state.history().groupBy("batch").count().where("count <> 20").count() == 0
    keyed = race.with_race_key(whole, weight="value", id_cols=["event_id"])
    bound = max(r.race_key for r in race.top_m(keyed, 20, ["event_id"]).collect())
    assert reservoir.prefilter(keyed, bound).count() == 20


def test_reservoir_goes_on_in_a_new_object(spark, sf, tmp_path):
    """A new object a batch, a batch that was cut short, a batch again, and rows twice in a batch."""
    events = spark.read.parquet(f"{sf}/events.parquet").where("value > 0")
    make = lambda: reservoir.StreamingRace(spark, 20, weight="value", id_cols=["event_id"], folder=str(tmp_path / "state"))
    parts = [events.where(F.col("event_id") % 4 == i) for i in range(4)]
    for batch, rows in enumerate(parts):
        make().foreach(rows.union(rows), batch)
    broken = tmp_path / "state" / "reservoir" / "batch=9"
    broken.mkdir()
    make().foreach(parts[3], 3)
    want = {(r.event_id, r.position) for r in race.race_sample(events, 20, weight="value", id_cols=["event_id"]).collect()}
    assert {(r.event_id, r.position) for r in make().sample().collect()} == want and make().batches() == [0, 1, 2, 3]
    make().read(3).withColumn("version", F.lit(reservoir.VERSION + 1)).write.parquet(make().path(5))
    with pytest.raises(ValueError, match="layout"):
        make().sample()


def wide(spark, n, seed=4):
    w = np.random.default_rng(seed).uniform(0.5, 9999, n)
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(w)], "item int, w double").repartition(3)


def test_quadrature_of_more_than_5000_items(spark):
    df = wide(spark, 9001)
    p, q = ({r.item: r.inclusion_prob for r in inclusion.draw_inclusion(df, 2, weight="w", id_cols=["item"], method=how).collect()} for how in ("quadrature", "m2"))
    assert len(p) == 9001 and max(abs(p[i] / q[i] - 1) for i in q) < 1e-10
    uneven = np.random.default_rng(1).pareto(0.7, 300) + 1e-3
    assert abs(inclusion.quadrature_draws(uneven, 10).sum() - 10) < 1e-9 and (inclusion.quadrature_draws(uneven, 10) <= 1).all()


def test_role_gap_of_more_than_5000_items(spark):
    """Against the chances of both roles worked out apart from Spark."""
    df = wide(spark, 5400)
    w = np.array([r.w for r in df.orderBy("item").collect()])
    want = np.abs(inclusion.quadrature_draws(w, 10) - 10 * w / w.sum())
    got = measures.role_gap(df, 10, weight="w", id_cols=["item"], method="quadrature").first()
    assert got.n == 5400 and got.max_gap == pytest.approx(want.max(), rel=1e-9) and got.total_gap == pytest.approx(want.sum(), rel=1e-9)


def test_pairs_in_rising_order(spark, monkeypatch):
    """Against all pairs, with equal ids, equal times and nulls, over many buckets; and more items than all pairs allow."""
    monkeypatch.setattr(measures, "BUCKET", 40)
    rng = np.random.default_rng(6)
    made = [[(int(i), None if rng.random() < 0.05 else float(y)) for i, y in zip(rng.integers(0, 150, n), rng.integers(0, 60, n), strict=True)] for n in (300, 260)]
    points, queries = (spark.createDataFrame(x, "i int, y double").repartition(3) for x in made)
    want = sum(i < j and y is not None and z is not None and y < z for i, y in made[0] for j, z in made[1])
    assert measures.dominated(points, queries) == want and measures.dominated(points.limit(0), queries) == 0
    assert measures.pair_count(points, F.col("i")) == sum(i < j for i, _ in made[0] for j, _ in made[0])
    monkeypatch.setattr(measures, "MOST_ITEMS", 100)
    df = wide(spark, 900)
    e = {r.item: r.e for r in df.select("item", (-F.ln(keyed_uniform(["item"], seed=1, tag="race", source="md5")) / F.col("w")).alias("e")).collect()}
    got = measures.pair_order_counts(df, weight="w", id_cols=["item"], seed=1, source="md5").first()
    assert tuple(got) == (900 * 899 // 2, sum(e[i] < e[j] for i in e for j in e if i < j))


def test_ratio_errors_of_many_items(spark, monkeypatch):
    """Against all pairs, with some chances off; more items than all pairs allow."""
    monkeypatch.setattr(measures, "MOST_ITEMS", 100)
    monkeypatch.setattr(measures, "BUCKET", 64)
    rng = np.random.default_rng(8)
    w = rng.uniform(1, 9, 400)
    p = w / w.sum() * np.where(rng.random(400) < 0.1, rng.choice([0.5, 1 + 1e-7, 1 - 1e-8, 2.0], 400), 1.0)
    df = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(zip(w, p, strict=True))], "item int, w double, p double").repartition(3)
    off = np.triu(np.abs(p[:, None] * w[None, :] - p[None, :] * w[:, None]) > 1e-9 * w[:, None], 1).sum()
    got = measures.ratio_errors(df, weight="w", chance="p", id_cols=["item"]).first()
    assert tuple(got) == (400 * 399 // 2, off) and 0 < off < got.n_pairs


def test_frequencies_of_many_items(spark, monkeypatch):
    """Every item has a row of each sampler, also one that is never hit, and more items than all pairs allow."""
    monkeypatch.setattr(measures, "MOST_ITEMS", 100)
    kinds = {"first": lambda w, m, rng: list(range(m)), "any": lambda w, m, rng: rng.choice(len(w), m, replace=False).tolist()}
    rows = measures.law_frequencies(wide(spark, 500), 3, 40, weight="w", id_cols=["item"], kinds=kinds).collect()
    by = {(r.sampler, r.item["item"]): r.hits for r in rows}
    assert len(rows) == len(by) == 1000 and [by["first", i] for i in range(5)] == [40, 40, 40, 0, 0]
    assert sum(by["any", i] for i in range(500)) == 120


def test_population_source_and_files(spark, tmp_path):
    population.register(spark)
    load = lambda parts: spark.read.format("weighted_population").option("rows", 150_000).option("partitions", parts).load()
    a = load(1).agg(F.count("*"), F.sum("weight"), F.min("weight")).first()
    b = load(3).agg(F.count("*"), F.sum("weight"), F.min("weight")).first()
    assert a[0] == b[0] == 150_000 and a[1] == pytest.approx(b[1]) and a[2] > 0
    df = items(spark, [1, 2, 3])
    for fmt in files.FORMATS:
        files.write(df, str(tmp_path / fmt), fmt)
        assert sorted(r.w for r in files.read(spark, str(tmp_path / fmt), fmt, schema="item int, w double").collect()) == [1, 2, 3]
    with pytest.raises(ValueError):
        files.read(spark, str(tmp_path / "csv"), "csv")
    files.append_reservoir(df, str(tmp_path / "log"), 1)
    files.append_reservoir(df, str(tmp_path / "log"), 1)
    assert spark.read.parquet(str(tmp_path / "log")).count() == 3


def test_linear_fit(spark):
    points = spark.createDataFrame([(float(x), 3.0 * x + 1) for x in range(9)], "x double, y double")
    got = measures.linear_fit(points, "x", "y")
    assert got["slope"] == pytest.approx(3) and got["r2"] == pytest.approx(1)
    assert measures.time_runs(lambda: points, runs=2)["runs"] == 2


def test_late_rows_do_not_reopen_windows(spark, tmp_path):
    rows = [(1, "2024-01-01 00:10:00", 5.0), (2, "2024-01-01 00:20:00", 1.0), (3, "2024-01-03 00:00:00", 1.0), (6, "2024-01-03 00:00:01", 1e-9), (4, "2024-01-01 00:30:00", 1e9), (5, "2024-01-05 00:00:00", 1.0)]
    schema = "event_id long, ts timestamp_ntz, value double"
    for part in (rows[:2], rows[2:3], rows[3:4], rows[4:5], rows[5:]):  # the filter of late rows follows a batch behind
        spark.createDataFrame(part, "event_id long, ts string, value double").selectExpr("event_id", "CAST(ts AS timestamp_ntz) ts", "value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    found = []
    out = reservoir.window_winner(stream, weight="value", id_col="event_id", time="ts", width="1 day").writeStream.outputMode("append").foreachBatch(lambda df, b: found.extend(df.collect()))
    run = out.option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert reservoir.late_rows(run) >= 1
    assert {r.event_id for r in found} <= {1, 2, 3} and {r.event_id for r in found} & {1, 2}
