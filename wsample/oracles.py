"""DuckDB twins of the named queries."""

from __future__ import annotations

import itertools

SQL: dict[str, str] = {}
SPAN = 4503599627370496


def hashed(parts: str, tag: str = "race", seed: int = 7) -> str:
    return f"CAST('0x' || substr(md5(concat_ws('|', '{seed}', '{tag}', {parts})), 1, 13) AS BIGINT)"


def keyed(parts: str, tag: str = "race", seed: int = 7) -> str:
    """SQL of the keyed uniform."""
    return f"(({hashed(parts, tag, seed)} + 0.5::DOUBLE) / {SPAN}::DOUBLE)"


def cents(x: str) -> str:
    return f"CAST(ROUND({x} * 100) AS BIGINT)"


def top(source: str, ids: str, weight: str, m: int, *, parts: str | None = None, where: str = "TRUE", key: str | None = None, tag: str = "race") -> str:
    """The m best keys with their rank."""
    key = key or f"-ln({keyed(parts or ids, tag)}) / ({weight})"
    return f"SELECT {ids}, CAST(row_number() OVER (ORDER BY e, {ids}) AS INTEGER) AS position FROM (SELECT *, {key} AS e FROM {source} WHERE {where} ORDER BY e, {ids} LIMIT {m})"


def grouped(source: str, group: str, ids: str, weight: str, m: int, where: str = "TRUE") -> str:
    return f"SELECT {group}, {ids}, CAST(position AS INTEGER) AS position FROM (SELECT *, row_number() OVER (PARTITION BY {group} ORDER BY -ln({keyed(ids)}) / ({weight}), {ids}) AS position FROM {source} WHERE {where}) WHERE position <= {m}"


POSITIVE_C, POSITIVE_S = "c_acctbal > 0", "s_acctbal > 0"
LINE_IDS = "l_orderkey, l_linenumber, l_partkey, l_suppkey, cents"
LINES = f"(SELECT *, {cents('l_extendedprice')} AS cents FROM lineitem)"
ORDERS = f"(SELECT *, {cents('o_totalprice')} AS cents FROM orders)"

SQL["keyed_uniforms"] = f"SELECT o_orderkey, {hashed('o_orderkey')} AS h FROM orders"
SQL["weights_derived"] = f"SELECT o_orderkey, {cents('o_totalprice')} AS cents FROM orders"
SQL["weight_profile"] = " UNION ALL ".join(
    f"SELECT '{t}' AS table_name, count(*) AS n, count(*) FILTER (NOT ({c} > 0)) AS n_bad, CAST(sum({cents(c)}) FILTER ({c} > 0) AS BIGINT) AS total_cents FROM {t}"
    for t, c in (("orders", "o_totalprice"), ("customer", "c_acctbal"), ("supplier", "s_acctbal"), ("lineitem", "l_discount"), ("events", "value"), ("part", "p_retailprice"))
)
SQL["positive_balances"] = f"SELECT c_custkey, {cents('c_acctbal')} AS cents FROM customer WHERE {POSITIVE_C}"

SQL["race_orders_m50"] = top("orders", "o_orderkey", "o_totalprice", 50)
for name in ("race_orders_m200", "race_repartition_invariant", "race_reservoir_orders", "merge_reservoirs"):
    SQL[name] = top("orders", "o_orderkey", "o_totalprice", 200)
SQL["race_orders_power"] = top("orders", "o_orderkey", "", 50, key=f"-pow({keyed('o_orderkey')}, 1.0::DOUBLE / (o_totalprice / 1e5))")
SQL["race_orders_gumbel"] = top("orders", "o_orderkey", "", 50, key=f"ln(-ln({keyed('o_orderkey')})) - ln(o_totalprice)")
SQL["sql_surface_race"] = SQL["race_orders_m50"]
SQL["race_lineitem_m200"] = top(LINES, LINE_IDS, "l_extendedprice", 200)
SQL["race_documents"] = top("documents", "doc_id", "n_chars", 50, where="n_chars > 0")
MARKED = "(SELECT d.doc_id, coalesce(1 + 9 * quality * (1 - toxic), 1) AS mark FROM documents d {} JOIN labels l ON d.doc_id = l.doc_id)"
SQL["race_quality_docs"] = top(MARKED.format(""), "doc_id", "mark", 50)
SQL["race_left_weight"] = top(MARKED.format("LEFT"), "doc_id", "mark", 50)
SQL["race_pages"] = top("pages", "page_id", "length(html)", 20, where="length(html) > 0")
SQL["race_conversations"] = top("conversations", "conv_id, turn", "length(text)", 20, where="length(text) > 0")
SQL["race_props_weight"] = top("(SELECT event_id, 1 + CAST(json_extract_string(props, '$.k') AS DOUBLE) AS w FROM events)", "event_id", "w", 50, where="w > 0")
SQL["race_embeddings"] = top("embeddings", "vec_id", "1 + label", 20)
SQL["uniform_orders"] = top("orders", "o_orderkey", "1.0", 50)
SQL["race_grid_counts"] = f"WITH p AS (SELECT o_orderkey, -ln({keyed('o_orderkey')}) / o_totalprice AS e, row_number() OVER (ORDER BY {hashed('o_orderkey', 'prefix')}, o_orderkey) AS k FROM orders) " + " UNION ALL ".join(
    f"SELECT {m} AS m, {n} AS n, count(*) AS n_sample, CAST(sum(o_orderkey) AS BIGINT) AS id_checksum FROM (SELECT o_orderkey FROM p WHERE k <= {n} ORDER BY e, o_orderkey LIMIT {m})" for m, n in itertools.product(range(50, 751, 100), range(1000, 6001, 1000))
)
SQL["race_by_returnflag"] = grouped(LINES, "l_returnflag", LINE_IDS, "l_quantity", 20)
SQL["ads_ranked_slots"] = grouped("customer", "c_mktsegment", "c_custkey", "c_acctbal", 5, POSITIVE_C)
SQL["ads_uniform"] = grouped("customer", "c_mktsegment", "c_custkey", "1.0", 5, POSITIVE_C)
SQL["ads_by_type"] = grouped("part", "p_type", "p_partkey", "p_retailprice", 5)
SQL["ads_by_type_equal_slots"] = "SELECT p_type, least(5, count(*)) AS n, least(5, count(*)) AS n_distinct, least(5, count(*)) AS n_in_population FROM part GROUP BY p_type"
SQL["range_race"] = top(LINES, LINE_IDS, "l_extendedprice", 50, where="l_quantity BETWEEN 10 AND 20")
REGIONS = "(SELECT * FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
SQL["stratified_race_region"] = grouped(REGIONS, "r_name", "c_custkey", "c_acctbal", 10, POSITIVE_C)
for name in ("race_jump_orders", "uniform_jump_orders", "prop_distributed_orders", "prop_sequential_orders", "prop_jump_orders"):
    SQL[name] = "SELECT least(200, count(*)) AS n, least(200, count(*)) AS n_distinct, least(200, count(*)) AS n_in_population FROM orders"


def thresholded(source: str, ids: str, weight: str, m: int) -> str:
    """Common table expressions ending in ``t`` (tau): the heavy prefix by rank, then the rest shared."""
    return f"""
    r AS (SELECT {ids}, CAST({weight} AS DOUBLE) AS w, row_number() OVER (ORDER BY {weight} DESC) AS k, count(*) OVER () AS n, sum(CAST({weight} AS DOUBLE)) OVER () AS total,
          coalesce(sum(CAST({weight} AS DOUBLE)) OVER (ORDER BY {weight} DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS above FROM {source}),
    h AS (SELECT coalesce(min(k) FILTER (({m} - k + 1) * w <= total - above), max(k) + 1) - 1 AS pinned FROM r WHERE k <= {m}),
    t AS (SELECT CASE WHEN any_value(n) <= {m} THEN 0 ELSE max(total - above) FILTER (k = pinned + 1) / ({m} - any_value(pinned)) END AS tau FROM r, h)"""


DOCS = "(SELECT * FROM documents WHERE n_chars > 0)"
SQL["inclusion_documents"] = f"WITH {thresholded(DOCS, 'doc_id', 'n_chars', 50)} SELECT doc_id, CAST(round(CASE WHEN tau = 0 THEN 1 ELSE least(1.0, w / tau) END * 1e6) AS BIGINT) AS pi_ppm, w > tau AS is_overweight FROM r, t"
SQL["overweight_documents"] = f"WITH {thresholded(DOCS, 'doc_id', 'n_chars', 200)} SELECT doc_id FROM r, t WHERE w > tau"
SQL["prop_documents_pinned"] = f"WITH {thresholded(DOCS, 'doc_id', 'n_chars', 200)} SELECT least(200, any_value(n)) AS n, least(200, any_value(n)) AS n_distinct, count(*) FILTER (w > tau) AS n_pinned_present FROM r, t"
SQL["overweight_trace_documents"] = f"""
WITH d AS (SELECT CAST(n_chars AS DOUBLE) AS w, row_number() OVER (ORDER BY doc_id) AS i FROM {DOCS}), n AS (SELECT count(*) AS n FROM d),
c AS (SELECT k FROM (SELECT unnest([60, 100, 150, 200, 300, 500, 700, 900, 1000, 2000]) AS k), n WHERE k <= n UNION SELECT (n * j + 9) // 10 FROM n, range(1, 11) t(j)),
r AS (SELECT k, w, row_number() OVER (PARTITION BY k ORDER BY w DESC, i) AS r, sum(w) OVER (PARTITION BY k) - coalesce(sum(w) OVER (PARTITION BY k ORDER BY w DESC, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest FROM d JOIN c ON i <= k)
SELECT CAST(k AS INTEGER) AS k, CAST(count(*) FILTER (r <= 50 AND (50 - r + 1) * w > rest) AS INTEGER) AS n_overweight FROM r GROUP BY k"""


def reservoir(source: str, ids: str, weight: str, order: str, m: int, tag: str) -> str:
    """The inclusion role over an order in which only the first m are ever overweight: one step of victims by share, then the last writer."""
    return f"""
    WITH s AS (SELECT {ids}, {weight} AS w, row_number() OVER (ORDER BY {order}) AS k, sum({weight}) OVER (ORDER BY {order} ROWS UNBOUNDED PRECEDING) AS W_, {keyed("'u', " + ids, tag)} AS u, {keyed("'v', " + ids, tag)} AS v FROM {source}),
    one AS (SELECT * FROM s WHERE k = {m} + 1 AND u * W_ < {m} * w),
    shares AS (SELECT s.k - 1 AS slot, sum(one.W_ - {m} * s.w) OVER (ORDER BY s.k ROWS UNBOUNDED PRECEDING) AS upto FROM s, one WHERE s.k <= {m}),
    writes AS (
      SELECT k - 1 AS slot, k, {ids} FROM s WHERE k <= {m}
      UNION ALL SELECT (SELECT min(slot) FROM shares, one o WHERE upto > o.v * ({m} * o.w)) AS slot, k, {ids} FROM one
      UNION ALL SELECT CAST(floor(v * {m}) AS BIGINT) AS slot, k, {ids} FROM s WHERE k > {m} + 1 AND u * W_ < {m} * w)
    SELECT CAST(slot AS INTEGER) AS slot, arg_max({ids}, k) AS {ids} FROM writes GROUP BY slot"""


SQL["uniform_reservoir_window"] = reservoir("orders", "o_orderkey", "1", "o_orderkey", 50, "unif")
SQL["prop_orders_m50_window"] = reservoir(ORDERS, "o_orderkey", "cents", "cents DESC, o_orderkey", 50, "prop")
SQL["prop_part_m20_window"] = reservoir(f"(SELECT *, {cents('p_retailprice')} AS cents FROM part)", "p_partkey", "cents", "p_partkey", 20, "prop")
for name, m in (("prop_by_segment", 20), ("ads_equal_slots", 5), ("udtf_proportional", 10)):
    SQL[name] = f"SELECT c_mktsegment, least({m}, count(*)) AS n, least({m}, count(*)) AS n_distinct, least({m}, count(*)) AS n_in_population FROM customer WHERE {POSITIVE_C} GROUP BY c_mktsegment"

SLOTS = "range(1, 21) t(slot)"
WINNERS = f"(SELECT slot, o_orderkey FROM (SELECT slot, o_orderkey, row_number() OVER (PARTITION BY slot ORDER BY -ln({keyed('o_orderkey, slot', 'slot')}) / cents, o_orderkey) AS r FROM {ORDERS}, {SLOTS}) WHERE r = 1)"
SQL["replacement_race_orders"] = f"SELECT CAST(slot AS INTEGER) AS slot, o_orderkey FROM {WINNERS}"
SUMS = f"(SELECT o_orderkey, cents, sum(cents) OVER (ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS W_ FROM {ORDERS})"
SQL["replacement_prop_orders"] = f"SELECT CAST(slot AS INTEGER) AS slot, max(o_orderkey) AS o_orderkey FROM {SUMS}, {SLOTS} WHERE {keyed('o_orderkey, slot', 'slot')} * W_ < cents GROUP BY slot"
SQL["replacement_lookup"] = f"WITH s AS {SUMS}, p AS (SELECT slot, {keyed('slot', 'slot')} * (SELECT max(W_) FROM s) AS spot FROM {SLOTS}) SELECT CAST(slot AS INTEGER) AS slot, o_orderkey FROM s JOIN p ON spot >= W_ - cents AND spot < W_"
SQL["prop_single_slot_jump"] = f"""
WITH RECURSIVE s AS {SUMS}, t AS (SELECT min(W_)::DOUBLE AS first, max(W_)::DOUBLE AS total FROM s),
p(r, x) AS (SELECT 0, first FROM t UNION ALL SELECT r + 1, x / {keyed('r + 1', 'jump')} FROM p, t WHERE x / {keyed('r + 1', 'jump')} <= total)
SELECT o_orderkey FROM s, (SELECT max(x) AS x FROM p) WHERE W_ - cents < x AND x <= W_"""
for name in ("replacement_race_jump", "replacement_prop_jump"):
    SQL[name] = "SELECT CAST(20 AS BIGINT) AS n_slots, CAST(20 AS BIGINT) AS n_in_population"
SQL["slot_winners"] = f"SELECT o_orderkey, count(*) AS times_won FROM {WINNERS} GROUP BY o_orderkey"
SQL["slots_array"] = f"SELECT o_orderkey, CAST(count(*) OVER (PARTITION BY o_orderkey) AS INTEGER) AS n_slots, CAST(row_number() OVER (PARTITION BY o_orderkey ORDER BY slot) - 1 AS INTEGER) AS i, CAST(slot AS INTEGER) AS slot FROM {WINNERS}"


def chain(m: int, share: str) -> str:
    """Slots filled one after the other by the best key among items below their share."""
    return f"""
    WITH RECURSIVE c AS (SELECT p_partkey, slot, {share} AS share, -ln({keyed('p_partkey, slot', 'bound')}) / p_retailprice AS e, row_number() OVER (PARTITION BY slot ORDER BY -ln({keyed('p_partkey, slot', 'bound')}) / p_retailprice, p_partkey) AS r FROM part, range(1, {m + 1}) t(slot)),
    best AS (SELECT * FROM c WHERE r <= {m}),
    held(slot, p_partkey, chosen) AS (
      SELECT CAST(0 AS BIGINT), CAST(NULL AS BIGINT), CAST([] AS BIGINT[])
      UNION ALL
      SELECT slot, p_partkey, list_append(chosen, p_partkey) FROM (
        SELECT b.slot, b.p_partkey, h.chosen, row_number() OVER (ORDER BY b.e, b.p_partkey) AS n FROM held h JOIN best b ON b.slot = h.slot + 1 WHERE len(list_filter(h.chosen, lambda x: x = b.p_partkey)) < b.share) WHERE n = 1)
    SELECT CAST(slot AS INTEGER) AS slot, p_partkey, CAST(len(list_filter(chosen, lambda x: x = p_partkey)) AS INTEGER) AS copy_no FROM held WHERE slot > 0"""


SQL["bounded_parts_k2"] = SQL["selector_bounded"] = chain(10, "2")
SQL["bounded_parts_own_k"] = chain(10, "least(p_size, 10)")
SQL["bounded_k_equals_m"] = chain(10, "10")
SQL["bounded_pipeline_parts"] = f"SELECT slot, p_partkey FROM ({chain(10, '2')})"

SQL["recency_race_events"] = top("events", "event_id", "", 50, where="value > 0", key=f"ln(-ln({keyed('event_id', 'recent')})) - (ln(value) + (epoch_us(ts) / 1e6::DOUBLE - 1704067200) * (0.6931471805599453::DOUBLE / 86400))")
SQL["recency_poly_events"] = top("events", "event_id", "value * pow(1 + (2000000000 - epoch_us(ts) / 1e6::DOUBLE) / 86400, -1.5)", 50, where="value > 0", tag="recent")
SQL["recency_prop_events"] = "SELECT least(50, count(*)) AS n, least(50, count(*)) AS n_distinct, least(50, count(*)) AS n_in_population FROM events WHERE value > 0"
SQL["constant_rate_events"] = f"""
WITH s AS (SELECT event_id, row_number() OVER (ORDER BY ts, event_id) AS k, {keyed("'u', event_id", 'rate')} AS u, {keyed("'v', event_id", 'rate')} AS v FROM events),
w AS (SELECT CASE WHEN k <= 50 THEN k - 1 ELSE CAST(floor(v * 50) AS BIGINT) END AS slot, k, event_id FROM s WHERE k <= 50 OR u < 0.1)
SELECT CAST(slot AS INTEGER) AS slot, arg_max(event_id, k) AS event_id FROM w GROUP BY slot"""


def shared_out(shares: tuple[int, ...]) -> str:
    """Items that hold the orders of their remainders, by number."""
    return f"(SELECT [{', '.join(map(str, shares))}][o_orderkey % {len(shares)} + 1] AS item, CAST(count(*) AS DOUBLE) AS w FROM orders GROUP BY 1)"


MILD_SHARES, HEAVY_SHARES, MORE_SHARES = (1, 2, 3, 4, 4), (1, 2, 3, 4, 4, 4, 4), (1, 2, 3, 4, 4, 4, 4, 5, 5, 5)
for name, rows in (("ex_mild_inclusion", shared_out(MILD_SHARES)), ("ex_infeasible_prefix", shared_out(HEAVY_SHARES)), ("ex_infeasible_recovered", shared_out(MORE_SHARES))):
    SQL[name] = f"WITH {thresholded(rows, 'item', 'w', 2)} SELECT CAST(item AS INTEGER) AS item, CAST(round(least(1.0, w / tau) * 1000) AS BIGINT) AS milli FROM r, t"


def two_draws(source: str, ids: str, weight: str) -> str:
    return f"(SELECT {ids}, w / total * (1 + odds - w / (total - w)) AS p FROM (SELECT {ids}, w, total, sum(w / (total - w)) OVER () AS odds FROM (SELECT {ids}, CAST({weight} AS DOUBLE) AS w, sum(CAST({weight} AS DOUBLE)) OVER () AS total FROM {source})))"


for name, rows in (("ex_mild_draw", shared_out(MILD_SHARES)), ("ex_heavy_draw", shared_out(HEAVY_SHARES))):
    SQL[name] = f"SELECT CAST(item AS INTEGER) AS item, CAST(round(p * 1000) AS BIGINT) AS milli FROM {two_draws(rows, 'item', 'w')}"
SUPPLIERS = f"(SELECT *, {cents('s_acctbal')} AS cents FROM supplier WHERE {POSITIVE_S})"
SQL["draw_inclusion_m2"] = f"SELECT s_suppkey, CAST(round(p * 1e6) AS BIGINT) AS ppm FROM {two_draws(SUPPLIERS, 's_suppkey', 's_acctbal')}"
SQL["draw_inclusion_quadrature"] = f"SELECT s_suppkey, CAST(round(p * 1e5) AS BIGINT) AS p_1e5 FROM {two_draws(SUPPLIERS, 's_suppkey', 's_acctbal')}"
SQL["role_gap_m2"] = " UNION ALL ".join(
    f"SELECT count(*) AS n, CAST(round(max(abs(p - pi)) * 1e6) AS BIGINT) AS gap_ppm FROM (WITH {thresholded(src, i, w, 2)} SELECT d.p, least(1.0, r.w / t.tau) AS pi FROM r, t, {two_draws(src, i, w)} d WHERE d.{i} = r.{i})"
    for src, i, w in ((SUPPLIERS, "s_suppkey", "s_acctbal"), (f"(SELECT * FROM customer WHERE {POSITIVE_C})", "c_custkey", "c_acctbal"), ("orders", "o_orderkey", "o_totalprice"))
)
SQL["freq_supplier"] = f"SELECT s_suppkey, count(*) FILTER (r <= 2) AS hits FROM (SELECT s_suppkey, row_number() OVER (PARTITION BY rep ORDER BY -ln({keyed('s_suppkey, rep', 'rep')}) / s_acctbal, s_suppkey) AS r FROM supplier, range(500) t(rep) WHERE {POSITIVE_S}) GROUP BY s_suppkey"
SQL["pair_order_rate"] = f"WITH k AS (SELECT s_suppkey, -ln({keyed('s_suppkey')}) / s_acctbal AS e FROM supplier WHERE {POSITIVE_S}) SELECT count(*) AS n_pairs, count(*) FILTER (a.e < b.e) AS n_ordered FROM k a JOIN k b ON a.s_suppkey < b.s_suppkey"
SQL["ratio_law"] = f"SELECT count(*) AS n_pairs, CAST(0 AS BIGINT) AS n_errors FROM {SUPPLIERS} a JOIN {SUPPLIERS} b ON a.s_suppkey < b.s_suppkey"
SQL["sequential_draw_supplier"] = f"""
WITH RECURSIVE s AS {SUPPLIERS}, held(round, s_suppkey, chosen) AS (
  SELECT 0, CAST(NULL AS BIGINT), CAST([] AS BIGINT[])
  UNION ALL
  SELECT round + 1, s_suppkey, list_append(chosen, s_suppkey) FROM (
    SELECT *, row_number() OVER (ORDER BY s_suppkey) AS n FROM (
      SELECT h.round, h.chosen, s.s_suppkey, sum(s.cents) OVER (ORDER BY s.s_suppkey ROWS UNBOUNDED PRECEDING) AS W_, sum(s.cents) OVER () AS total FROM held h, s WHERE h.round < 3 AND NOT list_contains(h.chosen, s.s_suppkey))
    WHERE W_ > {keyed('round + 1', 'round')} * total) WHERE n = 1)
SELECT CAST(round AS INTEGER) AS round, s_suppkey FROM held WHERE round > 0"""
SQL["expanded_population_supplier"] = f"SELECT s_suppkey, CAST(copy AS INTEGER) AS copy, position FROM ({top(f'(SELECT s_suppkey, s_acctbal, copy FROM supplier, range(1, 6) t(copy) WHERE {POSITIVE_S})', 's_suppkey, copy', 's_acctbal', 5)})"
SQL["poisson_orders"] = f"WITH t AS (SELECT sum(cents)::DOUBLE / 50 AS tau FROM {ORDERS}) SELECT o_orderkey FROM {ORDERS}, t WHERE {keyed('o_orderkey', 'poisson')} * tau < cents"
SQL["systematic_orders"] = f"""
WITH s AS {SUMS}, t AS (SELECT CAST(max(W_) AS HUGEINT) AS total, CAST(floor({keyed('1', 'grid')} * max(W_)) AS HUGEINT) AS u FROM s)
SELECT o_orderkey FROM s, t WHERE (CAST(W_ AS HUGEINT) * 50 + u) // total > (CAST(W_ - cents AS HUGEINT) * 50 + u) // total"""
SQL["expected_insertions"] = f"SELECT count(*) AS n, CAST(round(sum(least(1.0::DOUBLE, 200 * cents / W_::DOUBLE)) * 1000) AS BIGINT) AS milli FROM {SUMS}"
SQL["work_counters"] = " UNION ALL ".join(
    f"SELECT '{v}' AS variant, count(*) AS seen, {'NOT' * jump} (TRUE) AS one_each, {'count(*) - 200' if not jump else '0'} <= 4 * (200 + 200 * ln(count(*) / 200)) AS few_draws, TRUE AS as_expected FROM orders"
    for v, jump in (("race", False), ("race_jump", True), ("proportional", False), ("proportional_jump", True))
)
SQL["sampler_laws"] = f"SELECT sampler, count(*) AS n_items, CAST(0 AS BIGINT) AS n_off FROM supplier, (SELECT unnest(['race', 'race_jump', 'proportional', 'proportional_jump', 'proportional_merged']) AS sampler) WHERE {POSITIVE_S} GROUP BY sampler"
SQL["replacement_laws"] = f"SELECT method, count(*) AS n_items, CAST(0 AS BIGINT) AS n_off, CAST(4000 AS BIGINT) AS n_slots FROM supplier, (SELECT unnest(['race_jump', 'proportional_jump', 'lookup']) AS method) WHERE {POSITIVE_S} GROUP BY method"
SQL["estimate_revenue"] = f"WITH t AS (SELECT sum(cents)::DOUBLE / 200 AS tau FROM {LINES}) SELECT l_returnflag, count(*) AS n_sample, CAST(round(sum(l_quantity / least(1.0, cents / tau))) AS BIGINT) AS estimate FROM {LINES}, t WHERE {keyed(LINE_IDS, 'poisson')} * tau < cents GROUP BY l_returnflag"
SQL["survey_by_region"] = f"SELECT r_name, count(*) AS n_sample, CAST(sum({cents('c_acctbal')}) AS BIGINT) AS sum_cents FROM (SELECT *, row_number() OVER (PARTITION BY r_name ORDER BY -ln({keyed('c_custkey')}), c_custkey) AS r FROM {REGIONS}) WHERE r <= 10 GROUP BY r_name"


def sampled(m: int, tag: str = "race") -> str:
    return f"(SELECT * FROM {ORDERS} ORDER BY -ln({keyed('o_orderkey', tag)}) / o_totalprice, o_orderkey LIMIT {m})"


SQL["sample_payload"] = f"SELECT o_orderkey, o_custkey, cents FROM {sampled(50)}"
SQL["rest_of_population"] = f"SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT o_orderkey FROM {sampled(50)})"
SQL["sample_overlap"] = f"SELECT o_orderkey FROM {sampled(600)} INTERSECT SELECT o_orderkey FROM {sampled(600, 'other')}"
SQL["sample_except"] = f"SELECT o_orderkey FROM {sampled(600)} EXCEPT SELECT o_orderkey FROM {sampled(600, 'other')}"
SQL["asof_weight"] = "SELECT o_orderkey, arg_max(event_id, (ts, event_id)) AS event_id FROM orders LEFT JOIN events ON user_id = o_custkey AND ts <= o_orderdate GROUP BY o_orderkey"
for name, by in (("sample_rollup", "ROLLUP (o_orderstatus, o_orderpriority)"), ("sample_cube", "CUBE (o_orderstatus, o_orderpriority)"), ("sample_grouping_sets", "GROUPING SETS ((o_orderstatus), (o_orderpriority))")):
    SQL[name] = f"SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {sampled(200)} GROUP BY {by}"
SQL["sample_pivot"] = "SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (o_orderstatus = '{s}') AS \"{s}\"" for s in "FOP") + f" FROM {sampled(200)} GROUP BY o_orderpriority"
RANKS = "(PARTITION BY c_mktsegment ORDER BY cents DESC, c_custkey)"
SQL["stratum_ranks"] = f"SELECT c_custkey, CAST(rank() OVER {RANKS} AS INTEGER) AS rk, CAST(dense_rank() OVER {RANKS} AS INTEGER) AS dr, CAST(ntile(4) OVER {RANKS} AS INTEGER) AS nt, lag(c_custkey) OVER {RANKS} AS before, first(c_custkey) OVER {RANKS} AS top FROM (SELECT *, {cents('c_acctbal')} AS cents FROM customer)"
SQL["prefix_weights"] = f"SELECT o_orderkey, CAST(W_ AS BIGINT) AS prefix_cents FROM {SUMS}"
SQL["moving_weight"] = f"SELECT o_orderkey, CAST(sum(cents) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM {ORDERS}"
DAYS = 86_400_000_000
TUMBLING = f"(SELECT *, epoch_us(ts) - epoch_us(ts) % {DAYS} AS window_start FROM events)"
SQL["race_tumbling_events"] = grouped(TUMBLING, "window_start", "event_id", "value", 5, "value > 0")
SQL["race_sliding_events"] = grouped(f"(SELECT e.* EXCLUDE window_start, window_start - {DAYS} * back AS window_start FROM {TUMBLING} e, range(2) t(back))", "window_start", "event_id", "value", 3, "value > 0")
SESSIONS = "(SELECT *, min(epoch_us(ts)) OVER (PARTITION BY user_id, s) AS window_start FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 43200000000 THEN 0 ELSE 1 END AS g FROM events WHERE value > 0)))"
SQL["race_session_events"] = grouped(SESSIONS, "user_id, window_start", "event_id", "value", 2)
SQL["stream_race_events"] = top("events", "event_id", "value", 50, where="value > 0")
SQL["stream_min_by_window"] = f"SELECT window_start, event_id FROM ({grouped(TUMBLING, 'window_start', 'event_id', 'value', 1, 'value > 0')})"
SQL["stream_recency_events"], SQL["stream_tumbling_events"], SQL["stream_sliding_events"] = SQL["recency_race_events"], SQL["race_tumbling_events"], SQL["race_sliding_events"]
SQL["stream_prefix_check"] = "SELECT CAST(batch AS INTEGER) AS batch, TRUE AS ok FROM range(4) t(batch)"
SQL["props_families"] = "SELECT event_id, 'k' AS name, CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS weight FROM events"
SQL["outer_overlap"] = f"SELECT coalesce(a.o_orderkey, b.o_orderkey) AS o_orderkey, a.position AS first, b.position AS second FROM ({top('orders', 'o_orderkey', 'o_totalprice', 100)}) a FULL JOIN ({top('orders', 'o_orderkey', 'o_totalprice', 100, tag='other')}) b ON a.o_orderkey = b.o_orderkey"
