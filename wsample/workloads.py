"""Named queries over the given tables: (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wsample import samplers
from wsample.functions import sqlsurface
from wsample.functions.randomness import keyed_hash
from wsample.functions.times import micros
from wsample.functions.weights import cents, is_good
from wsample.operators import baselines, bounded, estimate, inclusion, kernels, measures, prefix, proportional, race, recency, replacement, select
from wsample.streaming import reservoir

SEED = 7
MD5 = {"seed": SEED, "source": "md5"}
QUERIES: dict = {}
LANDMARK, NOW, DAY = 1_704_067_200, 2_000_000_000, 86_400
GRID_M, GRID_N = tuple(range(50, 751, 100)), tuple(range(1000, 6001, 1000))
TRACE = (60, 100, 150, 200, 300, 500, 700, 900, 1000, 2000)


def query(f):
    QUERIES[f.__name__] = f
    return f


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _add(name: str, f) -> None:
    QUERIES[name] = f


def ids_of(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*cols, "position")


def _race(tab: str, m: int, weight, ids: list[str], prepare=lambda spark, sf, df: df, **kw):
    def run(spark, sf_dir):
        return ids_of(race.race_sample(prepare(spark, sf_dir, table(spark, sf_dir, tab)), m, weight=weight() if callable(weight) else weight, id_cols=ids, **{**MD5, **kw}), *ids)

    return run


def with_cents(spark, sf, df: DataFrame) -> DataFrame:
    return df.withColumn("cents", cents("l_extendedprice"))


def with_labels(how: str):
    def prepare(spark, sf, df: DataFrame) -> DataFrame:
        marks = table(spark, sf, "labels").select("doc_id", (1 + 9 * F.col("quality") * (1 - F.col("toxic"))).alias("mark"))
        return df.select("doc_id").join(marks, "doc_id", how).select("doc_id", F.coalesce(F.col("mark"), F.lit(1)).alias("mark"))

    return prepare


def positive(df: DataFrame, col: str) -> DataFrame:
    return df.where(is_good(col))


# weights and uniforms


@query
def keyed_uniforms(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", keyed_hash(["o_orderkey"], **MD5).alias("h"))


@query
def weights_derived(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", cents("o_totalprice").alias("cents"))


@query
def weight_profile(spark, sf_dir):
    parts = []
    for tab, col in (("orders", "o_totalprice"), ("customer", "c_acctbal"), ("supplier", "s_acctbal"), ("lineitem", "l_discount"), ("events", "value"), ("part", "p_retailprice")):
        good = is_good(col)
        parts.append(table(spark, sf_dir, tab).agg(F.lit(tab).alias("table_name"), F.count("*").alias("n"), F.count(F.when(~good, 1)).alias("n_bad"), F.sum(F.when(good, cents(col))).alias("total_cents")))
    return _union(parts)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query
def positive_balances(spark, sf_dir):
    return positive(table(spark, sf_dir, "customer"), "c_acctbal").select("c_custkey", cents("c_acctbal").alias("cents"))


# the race


_add("race_orders_m50", _race("orders", 50, "o_totalprice", ["o_orderkey"]))
_add("race_orders_m200", _race("orders", 200, "o_totalprice", ["o_orderkey"]))
_add("race_orders_power", _race("orders", 50, lambda: F.col("o_totalprice") / 1e5, ["o_orderkey"], form="power"))
_add("race_orders_gumbel", _race("orders", 50, "o_totalprice", ["o_orderkey"], form="gumbel"))
_add("race_repartition_invariant", _race("orders", 200, "o_totalprice", ["o_orderkey"], lambda spark, sf, df: df.repartition(17)))
_add("race_lineitem_m200", _race("lineitem", 200, "l_extendedprice", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cents"], with_cents))
_add("race_documents", _race("documents", 50, "n_chars", ["doc_id"], on_bad_weight="drop"))
_add("race_quality_docs", _race("documents", 50, "mark", ["doc_id"], with_labels("inner")))
_add("race_left_weight", _race("documents", 50, "mark", ["doc_id"], with_labels("left")))
_add("race_pages", _race("pages", 20, lambda: F.char_length("html"), ["page_id"], on_bad_weight="drop"))
_add("race_conversations", _race("conversations", 20, lambda: F.char_length("text"), ["conv_id", "turn"], on_bad_weight="drop"))
_add("race_props_weight", _race("events", 50, lambda: 1 + F.get_json_object("props", "$.k").cast("double"), ["event_id"], on_bad_weight="drop"))
_add("race_embeddings", _race("embeddings", 20, lambda: 1 + F.col("label"), ["vec_id"]))
_add("uniform_orders", _race("orders", 50, None, ["o_orderkey"]))


@query
def race_reservoir_orders(spark, sf_dir):
    return kernels.race_kernel(table(spark, sf_dir, "orders").repartition(5), 200, weight="o_totalprice", id_cols=["o_orderkey"], **MD5)


@query
def merge_reservoirs(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    parts = [race.race_sample(orders.where(F.col("o_orderkey") % 3 == r), 200, weight="o_totalprice", id_cols=["o_orderkey"], with_diagnostics=True, **MD5).select("o_orderkey", race.KEY) for r in range(3)]
    return ids_of(race.race_merge(parts, 200, ["o_orderkey"]), "o_orderkey")


@query
def race_grid_counts(spark, sf_dir):
    """All cells of n and m in one plan: each n's race is ranked once, and each m takes its first ranks."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", keyed_hash(["o_orderkey"], tag="prefix", **MD5).alias("h"))
    first = orders.orderBy("h", "o_orderkey").limit(max(GRID_N))  # the largest cell's rows
    ranked = first.withColumn("k", F.row_number().over(Window.orderBy("h", "o_orderkey")))
    keyed = race.with_race_key(ranked, weight="o_totalprice", id_cols=["o_orderkey"], **MD5)
    cells = keyed.withColumn("n", F.explode(F.array(*[F.lit(n) for n in GRID_N]))).where("k <= n")
    best = cells.withColumn("r", F.row_number().over(Window.partitionBy("n").orderBy(race.KEY, "o_orderkey"))).where(F.col("r") <= max(GRID_M))
    each = best.withColumn("m", F.explode(F.array(*[F.lit(m) for m in GRID_M]))).where("r <= m")
    return each.groupBy("m", "n").agg(F.count("*").alias("n_sample"), F.sum("o_orderkey").alias("id_checksum"))


@query
def race_by_returnflag(spark, sf_dir):
    rows = with_cents(spark, sf_dir, table(spark, sf_dir, "lineitem"))
    ids = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cents"]
    return race.race_by_group(rows, 20, ["l_returnflag"], weight="l_quantity", id_cols=ids, **MD5).select("l_returnflag", *ids, "position")


@query
def ads_ranked_slots(spark, sf_dir):
    return race.race_by_group(table(spark, sf_dir, "customer"), 5, ["c_mktsegment"], weight="c_acctbal", id_cols=["c_custkey"], on_bad_weight="drop", **MD5).select("c_mktsegment", "c_custkey", "position")


@query
def ads_uniform(spark, sf_dir):
    return race.race_by_group(positive(table(spark, sf_dir, "customer"), "c_acctbal"), 5, ["c_mktsegment"], weight=None, id_cols=["c_custkey"], **MD5).select("c_mktsegment", "c_custkey", "position")


@query
def ads_by_type(spark, sf_dir):
    """The second version of the ads: ranked links of each part type."""
    return race.race_by_group(table(spark, sf_dir, "part"), 5, ["p_type"], weight="p_retailprice", id_cols=["p_partkey"], **MD5).select("p_type", "p_partkey", "position")


@query
def ads_by_type_equal_slots(spark, sf_dir):
    parts = table(spark, sf_dir, "part")
    return _invariants(proportional.by_group(parts, 5, ["p_type"], weight="p_retailprice", id_cols=["p_partkey"], seed=SEED), parts, ["p_partkey"], ["p_type"])


@query
def range_race(spark, sf_dir):
    """A race among the rows of a range of an ordered column; the range reaches the scan."""
    rows = with_cents(spark, sf_dir, table(spark, sf_dir, "lineitem").where("l_quantity BETWEEN 10 AND 20"))
    ids = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cents"]
    return ids_of(race.race_sample(rows, 50, weight="l_extendedprice", id_cols=ids, **MD5), *ids)


def customers_by_region(spark, sf_dir) -> DataFrame:
    dims = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, sf_dir, "customer").join(dims, F.col("c_nationkey") == F.col("n_nationkey"))


@query
def stratified_race_region(spark, sf_dir):
    return race.race_by_group(customers_by_region(spark, sf_dir), 10, ["r_name"], weight="c_acctbal", id_cols=["c_custkey"], on_bad_weight="drop", **MD5).select("r_name", "c_custkey", "position")


def _invariants(sample: DataFrame, population: DataFrame, ids: list[str], by: list[str] | None = None) -> DataFrame:
    by = by or []
    known = population.select(*by, *ids).withColumn("known", F.lit(1))
    joined = sample.select(*by, *ids).join(known, [*by, *ids], "left")
    return joined.groupBy(*by).agg(F.count("*").alias("n"), F.countDistinct(*ids).alias("n_distinct"), F.count("known").alias("n_in_population"))


@query
def race_jump_orders(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return _invariants(kernels.race_kernel(orders.repartition(4), 200, weight="o_totalprice", id_cols=["o_orderkey"], seed=SEED, jump=True), orders, ["o_orderkey"])


@query
def uniform_jump_orders(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return _invariants(baselines.uniform_jump_sample(orders, 200, id_cols=["o_orderkey"], seed=SEED), orders, ["o_orderkey"])


# the inclusion role


@query
def inclusion_documents(spark, sf_dir):
    p = inclusion.inclusion_probabilities(table(spark, sf_dir, "documents"), 50, weight="n_chars", on_bad_weight="drop")
    return p.select("doc_id", F.round(F.col("inclusion_prob") * 1e6).cast("long").alias("pi_ppm"), "is_overweight")


@query
def overweight_documents(spark, sf_dir):
    return inclusion.inclusion_probabilities(table(spark, sf_dir, "documents"), 200, weight="n_chars", on_bad_weight="drop").where("is_overweight").select("doc_id")


@query
def overweight_trace_documents(spark, sf_dir):
    """The early prefixes of the trace, and tenths of the table up to all of it; items become overweight and are released."""
    docs = table(spark, sf_dir, "documents").where("n_chars > 0")
    n = docs.count()
    ks = sorted({k for k in TRACE if k <= n} | {(n * j + 9) // 10 for j in range(1, 11)})
    return inclusion.overweight_trace(docs, 50, ks, weight="n_chars", order=["doc_id"])


@query
def uniform_reservoir_window(spark, sf_dir):
    return proportional.windowed_sample(table(spark, sf_dir, "orders"), 50, weight=F.lit(1.0), id_cols=["o_orderkey"], order_by=["o_orderkey"], tag="unif", **MD5)


@query
def prop_orders_m50_window(spark, sf_dir):
    return proportional.windowed_sample(_orders_cents(spark, sf_dir), 50, weight="cents", id_cols=["o_orderkey"], order_by=[F.col("cents").desc(), F.col("o_orderkey")], tag="prop", **MD5)


@query
def prop_part_m20_window(spark, sf_dir):
    return proportional.windowed_sample(table(spark, sf_dir, "part").withColumn("cents", cents("p_retailprice")), 20, weight="cents", id_cols=["p_partkey"], order_by=["p_partkey"], tag="prop", **MD5)


@query
def prop_documents_pinned(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    sample = proportional.proportional_sample(docs.repartition(4), 200, weight="n_chars", id_cols=["doc_id"], seed=SEED, on_bad_weight="drop")
    pinned = inclusion.inclusion_probabilities(docs, 200, weight="n_chars", on_bad_weight="drop").where("is_overweight").select("doc_id", F.lit(1).alias("pin"))
    return sample.join(pinned, "doc_id", "left").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("n_distinct"), F.count("pin").alias("n_pinned_present"))


def _prop(mode: str):
    def run(spark, sf_dir):
        orders = table(spark, sf_dir, "orders")
        return _invariants(proportional.proportional_sample(orders.repartition(6), 200, weight="o_totalprice", id_cols=["o_orderkey"], mode=mode, seed=SEED), orders, ["o_orderkey"])

    return run


_add("prop_distributed_orders", _prop("distributed"))
_add("prop_sequential_orders", _prop("sequential"))
_add("prop_jump_orders", _prop("jump"))


@query
def prop_by_segment(spark, sf_dir):
    people = positive(table(spark, sf_dir, "customer"), "c_acctbal")
    return _invariants(proportional.by_group(people, 20, ["c_mktsegment"], weight="c_acctbal", id_cols=["c_custkey"], seed=SEED), people, ["c_custkey"], ["c_mktsegment"])


@query
def ads_equal_slots(spark, sf_dir):
    people = positive(table(spark, sf_dir, "customer"), "c_acctbal")
    return _invariants(proportional.by_group(people, 5, ["c_mktsegment"], weight="c_acctbal", id_cols=["c_custkey"], seed=SEED), people, ["c_custkey"], ["c_mktsegment"])


@query
def udtf_proportional(spark, sf_dir):
    from wsample.functions.udtf import register

    register(spark)
    people = positive(table(spark, sf_dir, "customer"), "c_acctbal")
    people.select("c_mktsegment", "c_custkey", "c_acctbal").createOrReplaceTempView("__people")
    found = spark.sql("SELECT stratum AS c_mktsegment, item AS c_custkey FROM proportional_reservoir(TABLE(SELECT c_mktsegment AS stratum, c_custkey AS item, c_acctbal AS weight, 10 AS m FROM __people) PARTITION BY stratum ORDER BY item)")
    return _invariants(found, people, ["c_custkey"], ["c_mktsegment"])


# with replacement and bounded


def _orders_cents(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", cents("o_totalprice").alias("cents"))


def _replaced(method: str):
    return lambda spark, sf_dir: replacement.replacement_sample(_orders_cents(spark, sf_dir), 20, weight="cents", id_cols=["o_orderkey"], method=method, **MD5)


for _m, _name in (("race", "replacement_race_orders"), ("proportional", "replacement_prop_orders"), ("lookup", "replacement_lookup")):
    _add(_name, _replaced(_m))


def _replaced_counts(method: str):
    def run(spark, sf_dir):
        orders = _orders_cents(spark, sf_dir)
        s = replacement.replacement_sample(orders.repartition(3), 20, weight="cents", id_cols=["o_orderkey"], method=method, seed=SEED)
        return s.join(orders, "o_orderkey", "left").agg(F.countDistinct("slot").alias("n_slots"), F.count("cents").alias("n_in_population"))

    return run


_add("replacement_race_jump", _replaced_counts("race_jump"))
_add("replacement_prop_jump", _replaced_counts("proportional_jump"))


@query
def prop_single_slot_jump(spark, sf_dir):
    return replacement.single_slot_jump(_orders_cents(spark, sf_dir), weight="cents", id_cols=["o_orderkey"], seed=SEED)


@query
def slot_winners(spark, sf_dir):
    return _replaced("race")(spark, sf_dir).groupBy("o_orderkey").agg(F.count("*").alias("times_won"))


@query
def slots_array(spark, sf_dir):
    held = _replaced("race")(spark, sf_dir).groupBy("o_orderkey").agg(F.array_sort(F.collect_list("slot")).alias("slots"))
    return held.select("o_orderkey", F.size("slots").alias("n_slots"), F.posexplode("slots").alias("i", "slot"))


def _parts(k, m: int = 10, method: str = "candidates"):
    return lambda spark, sf_dir: bounded.bounded_sample(table(spark, sf_dir, "part"), m, weight="p_retailprice", id_cols=["p_partkey"], k=k() if callable(k) else k, method=method, **MD5)


_add("bounded_parts_k2", _parts(2))
_add("bounded_parts_own_k", _parts(lambda: F.least(F.col("p_size"), F.lit(10))))
_add("bounded_k_equals_m", _parts(10))
_add("bounded_pipeline_parts", lambda spark, sf_dir: _parts(2, method="pipeline")(spark, sf_dir).select("slot", "p_partkey"))


@query
def selector_bounded(spark, sf_dir):
    return select.weighted_sample(table(spark, sf_dir, "part"), 10, weight="p_retailprice", id_cols=["p_partkey"], replacement=2, **MD5)


# recency


def _events(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "events").where("value > 0")


@query
def recency_race_events(spark, sf_dir):
    return ids_of(recency.recency_sample(_events(spark, sf_dir), 50, weight="value", id_cols=["event_id"], log_factor=recency.exp_decay("ts", half_life=DAY, landmark=LANDMARK), **MD5), "event_id")


@query
def recency_poly_events(spark, sf_dir):
    return ids_of(recency.recency_sample(_events(spark, sf_dir), 50, weight="value", id_cols=["event_id"], factor=recency.poly_decay("ts", now=NOW, power=1.5), **MD5), "event_id")


@query
def recency_prop_events(spark, sf_dir):
    events = _events(spark, sf_dir)
    latest = recency.seconds(F.lit(events.agg(F.max("ts")).first()[0]))
    s = recency.recency_sample(events, 50, weight="value", id_cols=["event_id"], log_factor=recency.exp_decay("ts", half_life=7 * DAY), landmark_shift=latest * (recency.LN2 / (7 * DAY)), role="inclusion", seed=SEED)
    return _invariants(s, events, ["event_id"])


@query
def constant_rate_events(spark, sf_dir):
    return recency.constant_rate_reservoir(table(spark, sf_dir, "events"), 50, 0.1, id_cols=["event_id"], order_by=["ts", "event_id"], **MD5)


# worked examples and measures


#: The item of each remainder of an order's key: items 1 to 3 have one share each, item 4 two or four, item 5 three.
MILD_SHARES, HEAVY_SHARES, MORE_SHARES = (1, 2, 3, 4, 4), (1, 2, 3, 4, 4, 4, 4), (1, 2, 3, 4, 4, 4, 4, 5, 5, 5)


def _example(shares, draw: bool):
    """Chances of a worked example's items at two draws.

    The items are groups of orders, dealt by key in the example's shares, and their weights are the orders they hold.
    """

    def run(spark, sf_dir):
        item = F.element_at(F.array(*map(F.lit, shares)), (F.col("o_orderkey") % len(shares) + 1).cast("int"))
        df = table(spark, sf_dir, "orders").groupBy(item.alias("item")).agg(F.count("*").cast("double").alias("weight"))
        p = inclusion.draw_inclusion(df, 2, weight="weight", id_cols=["item"], method="m2") if draw else inclusion.inclusion_probabilities(df, 2, weight="weight")
        return p.select("item", F.round(F.col("inclusion_prob") * 1000).cast("long").alias("milli"))

    return run


for _name, _rows, _draw in (("ex_mild_inclusion", MILD_SHARES, False), ("ex_mild_draw", MILD_SHARES, True), ("ex_infeasible_prefix", HEAVY_SHARES, False), ("ex_heavy_draw", HEAVY_SHARES, True), ("ex_infeasible_recovered", MORE_SHARES, False)):
    _add(_name, _example(_rows, _draw))


def _suppliers(spark, sf_dir) -> DataFrame:
    return positive(table(spark, sf_dir, "supplier"), "s_acctbal")


@query
def draw_inclusion_m2(spark, sf_dir):
    return inclusion.draw_inclusion(_suppliers(spark, sf_dir), 2, weight="s_acctbal", id_cols=["s_suppkey"], method="m2").select("s_suppkey", F.round(F.col("inclusion_prob") * 1e6).cast("long").alias("ppm"))


@query
def draw_inclusion_quadrature(spark, sf_dir):
    return inclusion.draw_inclusion(_suppliers(spark, sf_dir), 2, weight="s_acctbal", id_cols=["s_suppkey"], method="quadrature").select("s_suppkey", F.round(F.col("inclusion_prob") * 1e5).cast("long").alias("p_1e5"))


@query
def role_gap_m2(spark, sf_dir):
    cells = [(positive(table(spark, sf_dir, t), w), w, i) for t, w, i in (("supplier", "s_acctbal", "s_suppkey"), ("customer", "c_acctbal", "c_custkey"), ("orders", "o_totalprice", "o_orderkey"))]
    return _union([measures.role_gap_m2(df, weight=w, id_cols=[i]).select("n", F.round(F.col("max_gap") * 1e6).cast("long").alias("gap_ppm")) for df, w, i in cells])


@query
def role_gap_m10(spark, sf_dir):
    """(n, gap_ppm) at ten draws: by quadrature for the suppliers, in the large-n limit for the others."""
    cells = [("supplier", "s_acctbal", "s_suppkey", "quadrature"), ("customer", "c_acctbal", "c_custkey", "large_n"), ("orders", "o_totalprice", "o_orderkey", "large_n")]
    return _union([measures.role_gap(positive(table(spark, sf_dir, t), w), 10, weight=w, id_cols=[i], method=how).select("n", F.round(F.col("max_gap") * 1e6).cast("long").alias("gap_ppm")) for t, w, i, how in cells])


@query
def freq_supplier(spark, sf_dir):
    return measures.inclusion_frequency(_suppliers(spark, sf_dir), 2, 500, weight="s_acctbal", id_cols=["s_suppkey"], **MD5)


def _one_pass(kind):
    def run(weights, m, rng):
        sampler = kind(m, rng)
        half = len(weights) // 3
        sampler.offer(range(half), weights[:half])
        sampler.offer(range(half, len(weights)), weights[half:])
        return [e.item for e in sampler.snapshot()]

    return run


def _merged(weights, m, rng):
    """Three tasks' reservoirs, merged over adjusted weights."""
    parts = []
    for at in np.array_split(np.arange(len(weights)), 3):
        parts.append(samplers.ProportionalSampler(m, rng))
        parts[-1].offer(at.tolist(), weights[at])
    parts[0].merge(parts[1])
    parts[0].merge(parts[2])
    return [e.item for e in parts[0].snapshot()]


DRAW_KINDS = {"race": _one_pass(samplers.RaceSampler), "race_jump": _one_pass(samplers.RaceJumpSampler)}
INCLUSION_KINDS = {"proportional": _one_pass(samplers.ProportionalSampler), "proportional_jump": _one_pass(samplers.ProportionalJumpSampler), "proportional_merged": _merged}
LAW_RUNS, LAW_SLOTS = 1500, 4000


@query
def sampler_laws(spark, sf_dir):
    """(sampler, n_items, n_off): items whose frequency over many runs of a sampler is off its exact chance."""
    people, args = _suppliers(spark, sf_dir), {"weight": "s_acctbal", "id_cols": ["s_suppkey"]}
    out = []
    for kinds, chances in ((DRAW_KINDS, inclusion.draw_inclusion_m2(people, **args)), (INCLUSION_KINDS, inclusion.inclusion_probabilities(people, 2, weight="s_acctbal"))):
        hits = measures.law_frequencies(people, 2, LAW_RUNS, kinds=kinds, seed=SEED, **args).select("sampler", "item.s_suppkey", "hits")
        out.append(hits.join(chances.select("s_suppkey", F.col("inclusion_prob").alias("p")), "s_suppkey"))
    return _union(out).groupBy("sampler").agg(F.count("*").alias("n_items"), F.count(F.when(measures.beyond("hits", LAW_RUNS, "p"), 1)).alias("n_off"))


@query
def replacement_laws(spark, sf_dir):
    """(method, n_items, n_off): items that hold another number of many slots than their share of the weight, the first item among them."""
    people = _suppliers(spark, sf_dir).select("s_suppkey", "s_acctbal")
    total = people.agg(F.sum("s_acctbal")).first()[0]
    out = []
    for method in ("race_jump", "proportional_jump", "lookup"):
        slots = replacement.replacement_sample(people, LAW_SLOTS, weight="s_acctbal", id_cols=["s_suppkey"], method=method, seed=SEED)
        held = people.join(slots.groupBy("s_suppkey").agg(F.count("*").alias("hits")), "s_suppkey", "left").na.fill(0, ["hits"])
        off = measures.beyond("hits", LAW_SLOTS, F.col("s_acctbal") / F.lit(total))
        out.append(held.agg(F.lit(method).alias("method"), F.count("*").alias("n_items"), F.count(F.when(off, 1)).alias("n_off"), F.sum("hits").alias("n_slots")))
    return _union(out)


@query
def pair_order_rate(spark, sf_dir):
    return measures.pair_order_counts(_suppliers(spark, sf_dir), weight="s_acctbal", id_cols=["s_suppkey"], **MD5)


@query
def ratio_law(spark, sf_dir):
    p = inclusion.inclusion_probabilities(_suppliers(spark, sf_dir), 2, weight="s_acctbal").select("s_suppkey", "s_acctbal", F.col("inclusion_prob").alias("p"))
    return measures.ratio_errors(p, weight="s_acctbal", chance="p", id_cols=["s_suppkey"])


@query
def sequential_draw_supplier(spark, sf_dir):
    return baselines.sequential_draw(_suppliers(spark, sf_dir).withColumn("cents", cents("s_acctbal")), 3, weight="cents", id_cols=["s_suppkey"], seed=SEED)


@query
def expanded_population_supplier(spark, sf_dir):
    return baselines.expanded_sample(_suppliers(spark, sf_dir), 5, weight="s_acctbal", id_cols=["s_suppkey"], **MD5)


@query
def poisson_orders(spark, sf_dir):
    return baselines.poisson_sample(_orders_cents(spark, sf_dir), 50, weight="cents", id_cols=["o_orderkey"], **MD5).select("o_orderkey")


@query
def systematic_orders(spark, sf_dir):
    return baselines.systematic_sample(_orders_cents(spark, sf_dir), 50, units=F.col("cents"), id_cols=["o_orderkey"], seed=SEED).select("o_orderkey")


@query
def expected_insertions(spark, sf_dir):
    return measures.expected_insertions(_orders_cents(spark, sf_dir), 200, weight="cents", order_by=["o_orderkey"]).select("n", F.round(F.col("expected") * 1000).cast("long").alias("milli"))


@query
def work_counters(spark, sf_dir):
    """Draws and insertions in one task: whether draws are few (of order m log(n / m)), and insertions near their expectation."""
    orders, m = table(spark, sf_dir, "orders").coalesce(1), 200
    few = 4 * (m + m * F.ln(F.col("seen") / m))
    expected = m + m * F.ln(F.col("seen") / m)
    parts = []
    for v in ("race", "race_jump", "proportional", "proportional_jump"):
        done = kernels.totals(kernels.work(orders, m, weight="o_totalprice", variant=v, seed=SEED))
        parts.append(done.select(F.lit(v).alias("variant"), "seen", (F.col("draws") >= F.col("seen") - m).alias("one_each"), (F.col("draws") <= few).alias("few_draws"), F.col("insertions").between(0.75 * expected, 1.25 * expected).alias("as_expected")))
    return _union(parts)


@query
def estimate_revenue(spark, sf_dir):
    rows = with_cents(spark, sf_dir, table(spark, sf_dir, "lineitem"))
    ids = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cents"]
    tau, _ = inclusion.threshold(rows, 200, weight="cents")
    sample = baselines.poisson_sample(rows, 200, weight="cents", id_cols=ids, tau=tau, **MD5).withColumn("inclusion_prob", F.least(F.lit(1.0), F.col("cents") / F.lit(tau)))
    return estimate.estimate_total(sample, F.col("l_quantity"), by=["l_returnflag"]).select("l_returnflag", "n_sample", F.round("estimate").cast("long").alias("estimate"))


@query
def survey_by_region(spark, sf_dir):
    s = race.race_by_group(customers_by_region(spark, sf_dir), 10, ["r_name"], weight=None, id_cols=["c_custkey"], **MD5)
    return s.groupBy("r_name").agg(F.count("*").alias("n_sample"), F.sum(cents("c_acctbal")).alias("sum_cents"))


# operators around samples


def _sample_orders(spark, sf_dir, m: int = 200, tag: str = "race") -> DataFrame:
    return race.race_sample(table(spark, sf_dir, "orders"), m, weight="o_totalprice", id_cols=["o_orderkey"], tag=tag, **MD5)


@query
def sample_payload(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return race.late_payload(orders, _sample_orders(spark, sf_dir, 50), ["o_orderkey"]).select("o_orderkey", "o_custkey", cents("o_totalprice").alias("cents"))


@query
def rest_of_population(spark, sf_dir):
    return table(spark, sf_dir, "orders").join(_sample_orders(spark, sf_dir, 50), "o_orderkey", "left_anti").select("o_orderkey")


@query
def sample_overlap(spark, sf_dir):
    a, b = (_sample_orders(spark, sf_dir, 600, t).select("o_orderkey") for t in ("race", "other"))
    return a.intersect(b)


@query
def sample_except(spark, sf_dir):
    a, b = (_sample_orders(spark, sf_dir, 600, t).select("o_orderkey") for t in ("race", "other"))
    return a.exceptAll(b)


@query
def asof_weight(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select(F.col("o_custkey").cast("long").alias("who"), F.col("o_orderdate").cast("timestamp").alias("at"), F.lit(1).alias("kind"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    events = table(spark, sf_dir, "events").select(F.col("user_id").cast("long").alias("who"), F.col("ts").cast("timestamp").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("who").orderBy("at", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = orders.unionByName(events).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w))
    return both.where("kind = 1").select("o_orderkey", "event_id")


@query
def sample_rollup(spark, sf_dir):
    return _sample_orders(spark, sf_dir).rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query
def sample_cube(spark, sf_dir):
    return _sample_orders(spark, sf_dir).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query
def sample_grouping_sets(spark, sf_dir):
    _sample_orders(spark, sf_dir).createOrReplaceTempView("__sample_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM __sample_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")


@query
def sample_pivot(spark, sf_dir):
    return _sample_orders(spark, sf_dir).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


@query
def stratum_ranks(spark, sf_dir):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("cents"), "c_custkey")
    by = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", cents("c_acctbal").alias("cents"))
    return by.select("c_custkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.lag("c_custkey").over(w).alias("before"), F.first("c_custkey").over(w).alias("top"))


@query
def prefix_weights(spark, sf_dir):
    return prefix.running(_orders_cents(spark, sf_dir), ["o_orderkey"], {"prefix_cents": F.col("cents")}).select("o_orderkey", "prefix_cents")


@query
def moving_weight(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return table(spark, sf_dir, "orders").select("o_orderkey", F.sum(cents("o_totalprice")).over(w).alias("cents"))


@query
def sql_surface_race(spark, sf_dir):
    sqlsurface.register(spark)
    table(spark, sf_dir, "orders").createOrReplaceTempView("__orders")
    return spark.sql("""
        SELECT o_orderkey, CAST(row_number() OVER (ORDER BY e, o_orderkey) AS INT) AS position
        FROM (SELECT o_orderkey, race_key_log(concat_ws('|', '7', 'race', o_orderkey), o_totalprice) AS e FROM __orders ORDER BY e, o_orderkey LIMIT 50)
    """)


def _windowed(df: DataFrame, start: Column, m: int, by: list[str]) -> DataFrame:
    keyed = df.withColumn("window_start", start)
    return race.race_by_group(keyed, m, by, weight="value", id_cols=["event_id"], **MD5).select(*by, "event_id", "position")


@query
def race_tumbling_events(spark, sf_dir):
    return _windowed(_events(spark, sf_dir), micros(F.window("ts", "1 day")["start"]), 5, ["window_start"])


@query
def race_sliding_events(spark, sf_dir):
    rows = _events(spark, sf_dir).withColumn("w", F.window("ts", "2 days", "1 day"))
    return _windowed(rows, micros(F.col("w.start")), 3, ["window_start"])


@query
def race_session_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.when(micros("ts") - micros(F.lag("ts").over(w)) < 12 * 3600 * 1_000_000, 0).otherwise(1)
    rows = _events(spark, sf_dir).withColumn("g", gap).withColumn("s", F.sum("g").over(w))
    start = micros(F.min("ts").over(Window.partitionBy("user_id", "s")))
    return _windowed(rows, start, 2, ["user_id", "window_start"])


# streams


@query
def stream_race_events(spark, sf_dir):
    return reservoir.drain_race(spark, f"{sf_dir}/events.parquet", 50, weight="value", id_cols=["event_id"], keep="value > 0", **MD5)


@query
def stream_recency_events(spark, sf_dir):
    """Recency bias on a stream: keys against a fixed landmark, so that state is never written anew."""
    log_weight = F.ln("value") + recency.exp_decay("ts", half_life=DAY, landmark=LANDMARK)
    return reservoir.drain_race(spark, f"{sf_dir}/events.parquet", 50, weight="value", id_cols=["event_id"], keep="value > 0", tag="recent", form="gumbel", log_weight=log_weight, **MD5)


@query
def stream_tumbling_events(spark, sf_dir):
    found = reservoir.drain_window_reservoirs(spark, f"{sf_dir}/events.parquet", 5, keep="value > 0", weight="value", id_col="event_id", time="ts", width="1 day", width_us=DAY * 1_000_000, **MD5)
    return found.select("window_start", F.col("id").alias("event_id"), "position")


@query
def stream_sliding_events(spark, sf_dir):
    found = reservoir.drain_window_reservoirs(spark, f"{sf_dir}/events.parquet", 3, keep="value > 0", weight="value", id_col="event_id", time="ts", width="2 days", width_us=2 * DAY * 1_000_000, slide="1 day", **MD5)
    return found.select("window_start", F.col("id").alias("event_id"), "position")


@query
def stream_min_by_window(spark, sf_dir):
    return reservoir.drain_window_winner(spark, f"{sf_dir}/events.parquet", weight="value", id_col="event_id", time="ts", width="1 day", keep="value > 0", **MD5)


@query
def stream_prefix_check(spark, sf_dir):
    """Four files of events, in order: after each, the reservoir is the batch sample of all so far."""
    events = _events(spark, sf_dir)
    last = events.agg(F.max("event_id")).first()[0]
    cut = [last * (i + 1) // 4 for i in range(4)]
    state = reservoir.StreamingRace(spark, 50, weight="value", id_cols=["event_id"], **MD5)
    low = -1
    for high in cut:
        events.where((F.col("event_id") > low) & (F.col("event_id") <= high)).coalesce(1).write.mode("append").parquet(f"{state.folder}/in")
        low = high
    reservoir.drain(spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{state.folder}/in"), state)
    sample = lambda df: race.race_sample(df, 50, weight="value", id_cols=["event_id"], **MD5)
    return measures.prefix_check(state.history(), events, sample, batch="batch", order="event_id", ids=["event_id"], last=dict(enumerate(cut)))


@query
def weight_sketches(spark, sf_dir):
    """Sketches of a weight: distinct count, quantiles and a mergeable quantile sketch, for a first guess of thresholds."""
    orders = _orders_cents(spark, sf_dir)
    got = orders.agg(F.approx_count_distinct("cents").alias("n_distinct"), F.percentile_approx("cents", [0.5, 0.9, 0.99], 10_000).alias("q"), F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(cents), 0.5)").alias("kll_median"))
    return got.select("n_distinct", F.col("q")[0].alias("median"), F.col("q")[1].alias("p90"), F.col("q")[2].alias("p99"), "kll_median")


@query
def props_families(spark, sf_dir):
    """JSON, map and array functions around a weight."""
    parsed = table(spark, sf_dir, "events").select("event_id", F.from_json("props", "map<string,long>").alias("m"))
    made = parsed.select("event_id", F.map_entries(F.map_from_arrays(F.map_keys("m"), F.transform(F.map_values("m"), lambda x: x + 1))).alias("e"))
    flat = made.select("event_id", F.explode("e").alias("e")).select("event_id", F.col("e.key").alias("name"), F.col("e.value").alias("weight"))
    return flat.where(F.to_json(F.struct("weight")).isNotNull())


@query
def outer_overlap(spark, sf_dir):
    """Two samples side by side, a full outer join of whole-table hash joins."""
    a = _sample_orders(spark, sf_dir, 100).select("o_orderkey", F.col("position").alias("first")).hint("shuffle_hash")
    b = _sample_orders(spark, sf_dir, 100, "other").select("o_orderkey", F.col("position").alias("second"))
    return a.join(b, "o_orderkey", "full_outer")


@query
def spark_sample_contrast(spark, sf_dir):
    found = baselines.spark_samples(table(spark, sf_dir, "orders"), 0.1, seed=SEED)
    return _union([df.agg(F.lit(name).alias("method"), (F.count("*") > 0).alias("any_rows")) for name, df in found.items()])


