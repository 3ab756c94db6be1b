"""Operators around the methods: scans, filters, joins, aggregates, windows, sets, functions and streams.

Most are one SQL text that Spark and the oracle both run over views of the tables; where their dialects differ, or the
point is an API (broadcast hint, semi join, stream), the Spark side is written with DataFrames.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .sources.folders import new_folder as _folder
from .sources import tasks
from .streaming import fit as streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _run(sql: str):
    names = [t for t in tasks.TABLES if re.search(rf"\b{t}\b", sql)]
    return lambda spark, sf: tasks.views(spark, sf, names).sql(sql)


def add(name: str, spark_side, oracle: str | None = None) -> None:
    """A query; a text is SQL for both sides."""
    QUERIES[name] = _run(spark_side) if isinstance(spark_side, str) else spark_side
    if oracle or isinstance(spark_side, str):
        ORACLES[name] = oracle or spark_side


def t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return tasks.table(spark, sf, name)


_Z = "(0.2 - 0.3*value/100)"
_Y = "(CASE WHEN value > 50 THEN 1e0 ELSE -1e0 END)"

# --- scans and sinks: written and read again --------------------------------------------------------------------------


def _round_trip(kind: str, **options):
    def run(spark, sf):
        path = _folder(spark, f"sink-{kind}")
        p = t(spark, sf, "part").select("p_partkey", "p_size", "p_retailprice")
        getattr(p.write.options(**options), kind)(path)
        return getattr(spark.read.schema(p.schema).options(**options), kind)(path)

    return run


for _k, _name in (("parquet", "sink_parquet"), ("orc", "sink_orc"), ("json", "sink_json"), ("csv", "scan_csv_units")):
    add(_name, _round_trip(_k), "SELECT p_partkey, p_size, p_retailprice FROM part")


def _text_units(spark, sf):
    path = _folder(spark, "lines")
    e = t(spark, sf, "events")
    e.select(F.concat_ws(",", F.lit("1.0"), F.col("value").cast("string"))).write.text(path)
    return tasks.read_csv_units(spark, path).groupBy("label").agg(F.count("*").alias("n"), F.round(F.sum(F.col("features")[0]), 2).alias("total"))


add("scan_text_lines", _text_units, "SELECT 1e0 AS label, count(*) AS n, round(sum(value), 2) AS total FROM events")


def _libsvm(spark, sf):
    path = _folder(spark, "libsvm")
    t(spark, sf, "events").select(F.concat(F.when(F.col("value") > 50, "1").otherwise("-1"), F.lit(" 1:1.0 3:"), F.col("value").cast("string"))).write.text(path)
    u = tasks.densify(tasks.read_libsvm_units(spark, path))
    return u.groupBy("label").agg(F.count("*").alias("n"), F.round(F.sum(F.element_at("features", 3)), 2).alias("total"), F.sum(F.element_at("features", 2)).alias("zeros"))


add("scan_libsvm", _libsvm, f"SELECT {_Y} AS label, count(*) AS n, round(sum(value), 2) AS total, 0e0 AS zeros FROM events GROUP BY 1")
add("scan_parquet", lambda s, sf: t(s, sf, "lineitem").select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem")
add("scan_json_props", lambda s, sf: t(s, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")), "SELECT event_id, CAST(props->>'$.k' AS INT) AS k FROM events")
add("scan_file_metadata", lambda s, sf: t(s, sf, "orders").groupBy("_metadata.file_size").agg(F.count("*").alias("n")))
add("catalog_views", "SELECT (SELECT count(*) FROM region) AS region, (SELECT count(*) FROM nation) AS nation, (SELECT count(*) FROM customer) AS customer, (SELECT count(*) FROM supplier) AS supplier, (SELECT count(*) FROM conversations) AS conversations, (SELECT count(*) FROM benchmark) AS benchmark")

# --- projections and filters -------------------------------------------------------------------------------------------

for _name, _e in {
    "project_features": "l_quantity/50 AS x0, l_discount*10 AS x1, l_tax*12.5e0 AS x2",
    "project_bias": "1e0 AS x0, round(l_extendedprice/105000, 6) AS x1",
    "project_dot_product": "round(0.1e0 + 0.2e0*l_quantity + 0.3e0*l_discount, 6) AS z",
}.items():
    add(_name, f"SELECT l_orderkey, l_linenumber, {_e} FROM lineitem")
for _name, _e in {
    "project_margin": f"round({_Y}*{_Z}, 6) AS m",
    "project_hinge_loss": f"round(greatest(0e0, 1-{_Y}*{_Z}), 6) AS loss",
    "project_logistic_loss": f"round(ln(1+exp(-{_Y}*{_Z})), 6) AS loss",
    "project_squared_loss": f"round(pow({_Z}-{_Y}, 2), 6) AS loss",
    "project_coefficient_linear": f"round(2*({_Z}-{_Y}), 6) AS c",
    "project_coefficient_logistic": f"round(-{_Y}/(1+exp({_Y}*{_Z})), 6) AS c",
    "project_coefficient_hinge": f"CASE WHEN {_Y}*{_Z} < 1 THEN -{_Y} ELSE 0e0 END AS c",
    "case_label_pm1": f"{_Y} AS label",
    "fn_sigmoid": "round(1/(1+exp(-value/100)), 6) AS s",
    "fn_exp_log1p": "round(exp(-value/100), 6) AS e, round(ln(1+value), 6) AS l",
    "fn_sqrt_step": "round(1e0/sqrt(event_id+1), 6) AS step",
    "fn_ceil_floor_mod": "CAST(ceil(value) AS BIGINT) AS c, CAST(floor(value) AS BIGINT) AS f, event_id % 7 AS m",
    "fn_pow": "round(pow(value/100, 3), 6) AS p",
    "fn_round": "round(value, 1) AS r",
    "fn_trig_planted": "round(cos(event_id % 64), 6) AS c, round(sin(event_id % 64), 6) AS s",
    "fn_concat_ws": "concat_ws('-', event_type, CAST(user_id AS VARCHAR(20))) AS name",
    "fn_substr": "substr(event_type, 1, 3) AS head, length(event_type) AS n",
    "fn_hash_bucket": "md5(event_type) AS digest",
    "fn_levenshtein": "levenshtein(event_type, 'click') AS d",
    "fn_date_parts": "year(ts) AS y, month(ts) AS m, day(ts) AS d, hour(ts) AS h",
    "fn_date_trunc": "date_trunc('month', ts) AS month",
}.items():
    add(_name, f"SELECT event_id, {_e} FROM events")
ORACLES["fn_date_parts"] = "SELECT event_id, year(ts)::INT AS y, month(ts)::INT AS m, day(ts)::INT AS d, hour(ts)::INT AS h FROM events"
ORACLES["fn_levenshtein"] = "SELECT event_id, levenshtein(event_type, 'click')::INT AS d FROM events"
ORACLES["fn_substr"] = "SELECT event_id, substr(event_type, 1, 3) AS head, length(event_type)::INT AS n FROM events"
QUERIES["fn_date_trunc"] = lambda s, sf: t(s, sf, "events").select("event_id", F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month"))
ORACLES["fn_date_trunc"] = "SELECT event_id, strftime(date_trunc('month', ts), '%Y-%m-%d') AS month FROM events"
add("fn_days_between", "SELECT o_orderkey, datediff(o_orderdate, DATE '1992-01-01') AS days FROM orders", "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days FROM orders")


def _durations(spark, sf):
    from .plans.language import seconds

    return spark.createDataFrame([(x, seconds(x)) for x in ("90s", "2m", "1h30m", "1h1m1s")], "text string, seconds int")


add("fn_duration_parse", _durations, "SELECT * FROM (VALUES ('90s', 90), ('2m', 120), ('1h30m', 5400), ('1h1m1s', 3661)) v(text, seconds)")
for _name, _e in {
    "filter_margin_violations": f"{_Y}*{_Z} < 1",
    "filter_between": "value BETWEEN 10 AND 20",
    "filter_in": "event_type IN ('click', 'view', 'purchase')",
    "filter_like": "event_type LIKE '%c%'",
    "filter_null_nan": "value IS NOT NULL AND event_type IS NOT NULL",
    "filter_partition": "event_id % 8 = 3",
}.items():
    add(_name, f"SELECT event_id, value FROM events WHERE {_e}")
add("filter_hash_bernoulli", "SELECT event_id FROM events WHERE CAST(conv(substr(md5(concat_ws(':','7','1',CAST(event_id AS STRING))),1,8),16,10) AS BIGINT) < 429496729", "SELECT event_id FROM events WHERE ('0x'||substr(md5(concat_ws(':',7,1,event_id)),1,8))::BIGINT < 429496729")
add("distinct_labels", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")

# --- joins -------------------------------------------------------------------------------------------------------------

add("join_documents_labels", "SELECT d.doc_id, lang, quality, toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id")


def _dimensions(s, sf):
    """The dimensions are broadcast by their size, which Spark checks against its threshold."""
    o, c, n = t(s, sf, "orders"), t(s, sf, "customer"), t(s, sf, "nation")
    return o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


add("join_orders_customer_nation_broadcast", _dimensions, "SELECT n_name, count(*) AS orders, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey=c_custkey JOIN nation ON c_nationkey=n_nationkey GROUP BY n_name")
add("join_lineitem_orders_sortmerge", lambda s, sf: t(s, sf, "lineitem").join(t(s, sf, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey=o_orderkey GROUP BY 1")
add("join_semi_labelled_docs", lambda s, sf: t(s, sf, "documents").join(t(s, sf, "labels"), "doc_id", "left_semi").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
add("join_anti_unlabelled_docs", lambda s, sf: t(s, sf, "documents").join(t(s, sf, "labels"), "doc_id", "left_anti").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
add("join_left_outer_labels", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
add("join_full_outer_traces", "SELECT coalesce(a.k, b.k) AS k, a.n AS speculated, b.n AS ran FROM (SELECT event_id % 10 AS k, count(*) AS n FROM events WHERE event_id % 10 < 7 GROUP BY 1) a FULL OUTER JOIN (SELECT event_id % 10 AS k, count(*) AS n FROM events WHERE event_id % 10 > 3 GROUP BY 1) b ON a.k = b.k")


def _bands(s, sf):
    """A range join by equal buckets: each band names the thousands it touches, and a price meets those of its own."""
    bands = s.range(0, 10).select(F.col("id").alias("band"), (F.col("id") * 15000).alias("lo"), ((F.col("id") + 1) * 15000).alias("hi"))
    bands = bands.withColumn("k", F.explode(F.sequence((F.col("lo") / 1000).cast("long"), ((F.col("hi") - 1) / 1000).cast("long"))))
    price = t(s, sf, "lineitem").select("l_extendedprice", F.floor(F.col("l_extendedprice") / 1000).alias("k"))
    return price.join(bands, "k").where((F.col("l_extendedprice") >= F.col("lo")) & (F.col("l_extendedprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


add("join_range_price_band", _bands, "SELECT band, count(*) AS n FROM lineitem JOIN range(10) r(band) ON l_extendedprice >= band*15000 AND l_extendedprice < (band+1)*15000 GROUP BY band")
add("join_cross_plan_space", "SELECT a.x AS algorithm, b.x AS sampler FROM (VALUES ('mgd'), ('sgd')) a(x) CROSS JOIN (VALUES ('bernoulli'), ('random'), ('shuffle')) b(x)")


def _asof(s, sf):
    """The last purchase before each event of a user: a union-free window over one pass of the user's events."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    bought = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return t(s, sf, "events").select("event_id", bought.alias("previous"))


add("join_asof_event_previous", _asof, "SELECT event_id, last_value(CASE WHEN event_type='purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS previous FROM events")
add("join_interval_events", "SELECT a.event_type AS a, b.event_type AS b, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTES GROUP BY 1, 2")
add("join_weights_by_index", "WITH x AS (SELECT event_id, 0 AS j, 1e0 AS v FROM events UNION ALL SELECT event_id, 1, value/100 FROM events), w AS (SELECT * FROM (VALUES (0, 0.2e0), (1, -0.3e0)) q(j, w)) SELECT event_id, round(sum(v*w), 6) AS z FROM x JOIN w ON x.j = w.j GROUP BY event_id")
add("join_state_literal", "SELECT round(sum(w0 + w1*value/100), 4) AS z FROM events CROSS JOIN (SELECT 0.2e0 AS w0, -0.3e0 AS w1) s")

# --- aggregates --------------------------------------------------------------------------------------------------------

_E = "FROM events"
for _name, _sql in {
    "agg_gradient_linear": f"SELECT round(sum(2*({_Z}-{_Y})), 4) AS g0, round(sum(2*({_Z}-{_Y})*value/100), 4) AS g1 {_E}",
    "agg_gradient_logistic": f"SELECT round(sum(-{_Y}/(1+exp({_Y}*{_Z}))), 4) AS g0, round(sum(-{_Y}/(1+exp({_Y}*{_Z}))*value/100), 4) AS g1 {_E}",
    "agg_gradient_hinge": f"SELECT round(sum(CASE WHEN {_Y}*{_Z}<1 THEN -{_Y} ELSE 0e0 END), 4) AS g0 {_E}",
    "agg_objective": f"SELECT round(avg(greatest(0e0, 1-{_Y}*{_Z})), 6) AS f {_E}",
    "agg_stage_stats": "SELECT count(*) AS n, round(avg(l_tax), 6) AS m, round(stddev_pop(l_tax), 6) AS s, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem",
    "agg_gram_matrix": "SELECT round(sum(l_quantity*l_quantity), 2) AS a, round(sum(l_quantity*l_tax), 2) AS b, round(sum(l_tax*l_tax), 4) AS c FROM lineitem",
    "agg_partial_per_partition": "SELECT sum(s) AS total, CAST(sum(n) AS BIGINT) AS n FROM (SELECT event_id % 8 AS p, round(sum(value), 2) AS s, count(*) AS n FROM events GROUP BY 1) q",
    "agg_mse": f"SELECT round(avg(pow({_Z}-{_Y}, 2)), 6) AS mse {_E}",
    "agg_label_balance": "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY quality, toxic",
    "agg_confusion_matrix": f"SELECT {_Y} AS label, CASE WHEN {_Z} >= 0 THEN 1e0 ELSE -1e0 END AS prediction, count(*) AS n {_E} GROUP BY 1, 2",
    "agg_precision_recall_f1": f"SELECT round(tp/p, 6) AS precision, round(tp/q, 6) AS recall, round(2*tp/(p+q), 6) AS f1 FROM (SELECT sum(CASE WHEN value > 50 AND value < 60 THEN 1e0 ELSE 0e0 END) AS tp, sum(CASE WHEN value < 60 THEN 1e0 ELSE 0e0 END) AS p, sum(CASE WHEN value > 50 THEN 1e0 ELSE 0e0 END) AS q {_E}) c",
    "agg_density": "SELECT round(avg(CASE WHEN l_discount <> 0 THEN 1e0 ELSE 0e0 END), 6) AS density FROM lineitem",
    "agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "agg_pivot": "SELECT user_id, sum(CASE WHEN event_type='click' THEN value ELSE 0e0 END) AS click, sum(CASE WHEN event_type='view' THEN value ELSE 0e0 END) AS view_ FROM (SELECT user_id, event_type, round(sum(value), 2) AS value FROM events GROUP BY 1, 2) q GROUP BY user_id",
    "agg_min_by_plan": "SELECT event_type, min_by(event_id, value + event_id*1e-9) AS best FROM events GROUP BY event_type",
    "agg_regr_slope": "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 2) AS intercept FROM lineitem",
    "agg_partition_catalog": "SELECT l_orderkey % 16 AS part_id, count(*) AS n_units FROM lineitem GROUP BY 1",
    "agg_corr": "SELECT round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem",
    "agg_keyed_sparse_gradient": "SELECT j, round(sum(v), 4) AS g FROM (SELECT event_id % 32 AS j, value/100 AS v FROM events) x GROUP BY j",
    "agg_charge_summary": "SELECT l_returnflag, l_linestatus, round(sum(l_extendedprice*(1-l_discount)), 2) AS sum_disc, round(avg(l_quantity), 6) AS avg_qty, count(*) AS n FROM lineitem GROUP BY 1, 2",
}.items():
    add(_name, _sql)
_TOKENS = "SELECT doc_id, explode(split(lower(text), '[ \n\t]+')) AS w FROM documents"
_TOKENS_D = "SELECT doc_id, unnest(string_split_regex(lower(text), '[ \n\t]+')) AS w FROM documents"
add("agg_distinct_tokens", f"SELECT count(DISTINCT w) AS n FROM ({_TOKENS}) WHERE w <> ''", f"SELECT count(DISTINCT w) AS n FROM ({_TOKENS_D}) WHERE w <> ''")
add("fn_tokenize", f"SELECT w, count(*) AS n FROM ({_TOKENS}) WHERE w <> '' GROUP BY w", f"SELECT w, count(*) AS n FROM ({_TOKENS_D}) WHERE w <> '' GROUP BY w")
add("agg_approx_distinct_tokens", lambda s, sf: s.createDataFrame([(tasks.views(s, sf, ["documents"]).sql(f"SELECT approx_count_distinct(w) FROM ({_TOKENS})").first()[0],)], "n long"))
add("agg_percentile", "SELECT round(percentile(value, 0.5), 6) AS p50, round(percentile(value, 0.9), 6) AS p90 FROM events", "SELECT round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events")
add("agg_approx_percentile", lambda s, sf: t(s, sf, "events").agg(F.percentile_approx("value", 0.5).alias("p50")))
add("agg_sketch_hll", lambda s, sf: t(s, sf, "events").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users")))
add("agg_histogram", "SELECT width_bucket(value, 0, 200, 10) AS b, count(*) AS n FROM events GROUP BY 1", "SELECT least(greatest(floor(value/20)+1, 0), 11)::BIGINT AS b, count(*) AS n FROM events GROUP BY 1")

# --- windows, sorts, sets ----------------------------------------------------------------------------------------------

_OW = "OVER (PARTITION BY event_type ORDER BY event_id"
for _name, _e in {
    "win_rank_plans": "rank() OVER (PARTITION BY event_type ORDER BY value) AS r, dense_rank() OVER (PARTITION BY event_type ORDER BY value) AS d, row_number() OVER (PARTITION BY event_type ORDER BY value, event_id) AS n",
    "win_lag_delta": f"round(value - lag(value) {_OW}), 6) AS delta",
    "win_lead_event": f"lead(event_id) {_OW}) AS following",
    "win_monotone_envelope": f"min(value) {_OW} ROWS UNBOUNDED PRECEDING) AS low",
    "win_moving_average_loss": f"round(avg(value) {_OW} ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean",
    "win_first_last_value": f"first_value(value) {_OW}) AS head, last_value(value) {_OW} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS tail",
    "win_ntile_folds": f"ntile(5) {_OW}) AS fold",
    "win_cumulative_units": f"count(*) {_OW} ROWS UNBOUNDED PRECEDING) AS units",
    "win_percent_rank": "round(percent_rank() OVER (PARTITION BY event_type ORDER BY value), 6) AS p, round(cume_dist() OVER (PARTITION BY event_type ORDER BY value), 6) AS c",
}.items():
    add(_name, f"SELECT event_id, {_e} FROM events")
for _k, _cols in (("win_rank_plans", ("r", "d", "n")), ("win_ntile_folds", ("fold",))):
    ORACLES[_k] = f"SELECT event_id, {', '.join(f'{c}::INT AS {c}' for c in _cols)} FROM ({ORACLES[_k]})"


def _range_time(s, sf):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-3600, 0)
    return t(s, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", F.count("*").over(w).alias("n"))


add("win_range_time", _range_time, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
add("sort_shuffle_order", "SELECT event_id, row_number() OVER (PARTITION BY event_id % 8 ORDER BY md5(CAST(event_id AS STRING)), event_id) AS place FROM events", "SELECT event_id, (row_number() OVER (PARTITION BY event_id % 8 ORDER BY md5(event_id::VARCHAR), event_id))::INT AS place FROM events")
add("topk_weights", "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 20")
add("topk_losses_per_label", "SELECT event_type, event_id, value FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS k FROM events) q WHERE k <= 3")
add("limit_offset_batch", "SELECT event_id FROM events ORDER BY event_id LIMIT 100 OFFSET 200")
add("sort_nulls_last", "SELECT doc_id, quality FROM (SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) q ORDER BY quality DESC NULLS LAST, doc_id LIMIT 50")
_A, _B = "SELECT user_id FROM events WHERE event_type = 'click'", "SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 100"
for _name, _op in (("union_distinct", "UNION"), ("union_speculation_traces", "UNION ALL"), ("intersect_vocab", "INTERSECT"), ("except_vocab", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    add(_name, f"{_A} {_op} {_B}")
add("unionByName_missing", lambda s, sf: t(s, sf, "nation").select("n_name").unionByName(t(s, sf, "region").select(F.col("r_name").alias("n_name"), F.col("r_regionkey").cast("long").alias("k")), allowMissingColumns=True), "SELECT n_name, NULL::BIGINT AS k FROM nation UNION ALL SELECT r_name, r_regionkey FROM region")

# --- arrays, maps, JSON ------------------------------------------------------------------------------------------------


def _arrays(expr, out: str):
    return lambda s, sf: t(s, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v")).select("vec_id", expr(F.col("v")).alias(out))


_V = "SELECT vec_id, {e} FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings)"
add("fn_array_sum", _arrays(lambda v: F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + x), 5) + 0.0, "s"), _V.format(e="round(list_sum(v), 5) + 0.0 AS s"))
add("fn_l1_norm", _arrays(lambda v: F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + F.abs(x)), 5), "n"), _V.format(e="round(list_sum(list_transform(v, lambda x: abs(x))), 5) AS n"))
add("fn_l2_norm", _arrays(lambda v: F.round(F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x)), 5), "n"), _V.format(e="round(sqrt(list_dot_product(v, v)), 5) AS n"))
add("fn_linf_norm", _arrays(lambda v: F.round(F.array_max(F.transform(v, F.abs)), 6), "n"), _V.format(e="round(list_max(list_transform(v, lambda x: abs(x))), 6) AS n"))
add("fn_array_filter_nonzero", _arrays(lambda v: F.size(F.filter(v, lambda x: x > 0)), "n"), _V.format(e="len(list_filter(v, lambda x: x > 0))::INT AS n"))
add("fn_array_slice", _arrays(lambda v: F.round(F.slice(v, 3, 2)[1], 6), "x"), _V.format(e="round(v[4], 6) AS x"))
add("fn_zip_with_axpy", _arrays(lambda v: F.round(F.aggregate(F.zip_with(v, F.reverse(v), lambda a, b: a - 0.5 * b), F.lit(0.0), lambda s, x: s + x * x), 5), "q"), _V.format(e="round(list_sum(list_transform(range(1, 65), lambda i: pow(v[i] - 0.5*v[65-i], 2))), 5) AS q"))
add("fn_array_transform", _arrays(lambda v: F.round(F.array_max(F.transform(v, lambda x: x * 2)), 6), "m"), _V.format(e="round(list_max(v)*2, 6) AS m"))
add("fn_posexplode_sparse", lambda s, sf: t(s, sf, "embeddings").select("vec_id", F.posexplode(F.slice(F.col("embedding").cast("array<double>"), 1, 4)).alias("j", "x")).select("vec_id", "j", F.round("x", 6).alias("x")), "SELECT vec_id, j::INT AS j, round(embedding[j+1]::DOUBLE, 6) AS x FROM embeddings, range(4) r(j)")
add("fn_sequence", "SELECT explode(sequence(1, 20)) AS i", "SELECT i::INT AS i FROM range(1, 21) r(i)")
add("fn_collect_array", "SELECT event_type, size(collect_set(user_id)) AS n FROM events GROUP BY event_type", "SELECT event_type, count(DISTINCT user_id)::INT AS n FROM events GROUP BY event_type")
add("fn_map_from_arrays", lambda s, sf: t(s, sf, "events").select("event_id", F.map_from_arrays(F.array(F.lit(0), F.lit(3)), F.array(F.lit(1.0), F.col("value"))).alias("m")).select("event_id", F.col("m")[3].alias("x")), "SELECT event_id, value AS x FROM events")
add("fn_map_keys_values", lambda s, sf: t(s, sf, "events").groupBy("event_type").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select(F.explode("m").alias("event_type", "n")), "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
add("fn_map_zip_with", lambda s, sf: t(s, sf, "events").select("event_id", F.map_zip_with(F.create_map(F.lit("a"), F.col("value")), F.create_map(F.lit("a"), F.lit(2.0)), lambda k, x, y: x * y)["a"].alias("x")), "SELECT event_id, value*2 AS x FROM events")
add("fn_json_extract", lambda s, sf: t(s, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")), "SELECT event_id, CAST(props->>'$.k' AS INT) AS k FROM events")
add("fn_to_json_model", lambda s, sf: t(s, sf, "nation").select(F.to_json(F.struct(F.col("n_name").alias("name"))).alias("j")), "SELECT '{\"name\":\"'||n_name||'\"}' AS j FROM nation")
add("fn_html_strip", lambda s, sf: t(s, sf, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n")), "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INT AS n FROM pages")

# --- user functions ----------------------------------------------------------------------------------------------------


def _pandas_margin(s, sf):
    @F.pandas_udf("double")
    def margin(v: pd.Series) -> pd.Series:
        return 0.2 - 0.3 * v / 100

    return t(s, sf, "events").select("event_id", F.round(margin("value"), 6).alias("z"))


add("udf_pandas_margin", _pandas_margin, f"SELECT event_id, round({_Z}, 6) AS z FROM events")


def _pandas_gradient(s, sf):
    @F.pandas_udf("double")
    def gradient(v: pd.Series) -> float:
        return float((2 * (0.2 - 0.3 * v / 100 - 1)).sum())

    return t(s, sf, "events").groupBy("event_type").agg(F.round(gradient("value"), 3).alias("g"))


add("udaf_pandas_gradient", _pandas_gradient, f"SELECT event_type, round(sum(2*({_Z}-1)), 3) AS g FROM events GROUP BY 1")


def _udtf(s, sf):
    from .plans.space import enumerate_plans

    keys = [(p.key, p.algorithm) for p in enumerate_plans()]

    @F.udtf(returnType="plan string, algorithm string")
    class ExplainPlans:
        def eval(self):
            yield from keys

    return ExplainPlans()


add("udtf_explain_plans", _udtf, "SELECT * FROM (VALUES ('bgd','bgd'), ('mgd-eager-bernoulli','mgd'), ('mgd-eager-random','mgd'), ('mgd-eager-shuffle','mgd'), ('mgd-lazy-random','mgd'), ('mgd-lazy-shuffle','mgd'), ('sgd-eager-bernoulli','sgd'), ('sgd-eager-random','sgd'), ('sgd-eager-shuffle','sgd'), ('sgd-lazy-random','sgd'), ('sgd-lazy-shuffle','sgd')) v(plan, algorithm)")

# --- streams: events replayed to the end of a stream -------------------------------------------------------------------


def _text(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm"))


_DAY = "strftime({w}, '%Y-%m-%d %H:%M') AS start"
add("stream_tumbling_loss", lambda s, sf: _text(streams.replay(s, sf, lambda e: streams.windowed(e, "tumbling"), _folder(s, "ckpt"))).select("start", "n", F.round("mean_value", 6).alias("mean_value")), f"SELECT {_DAY.format(w='time_bucket(INTERVAL 1 DAY, ts)')}, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY 1")
add("stream_sliding_loss", lambda s, sf: _text(streams.replay(s, sf, lambda e: streams.windowed(e, "sliding"), _folder(s, "ckpt"))).select("start", "n", F.round("mean_value", 6).alias("mean_value")), f"SELECT {_DAY.format(w='w')}, count(*) AS n, round(avg(value), 6) AS mean_value FROM (SELECT value, time_bucket(INTERVAL 6 HOURS, ts) - k*INTERVAL 6 HOURS AS w FROM events, range(4) r(k)) GROUP BY w")
add("stream_session_user", lambda s, sf: streams.replay(s, sf, lambda e: streams.windowed(e, "session"), _folder(s, "ckpt"), mode="complete").select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n"), "WITH g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTES THEN 1 ELSE 0 END AS new FROM events)) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM g GROUP BY user_id, s")
add("stream_dedup", lambda s, sf: streams.replay(s, sf, lambda e: e.union(e).dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), _folder(s, "ckpt"), mode="append"), "SELECT event_id FROM events")
add("stream_predict", lambda s, sf: streams.replay(s, sf, lambda e: e.select("event_id", F.round(F.lit(0.2) - 0.3 * F.col("value") / 100, 6).alias("z")), _folder(s, "ckpt"), mode="append"), f"SELECT event_id, round({_Z}, 6) AS z FROM events")
add("stream_static_join", lambda s, sf: streams.replay(s, sf, lambda e: e.join(t(s, sf, "nation"), e.event_id % 25 == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), _folder(s, "ckpt")), "SELECT n_name, count(*) AS n FROM events JOIN nation ON event_id % 25 = n_nationkey GROUP BY 1")


def _stream_sgd(s, sf):
    """One micro-batch: the stream of one file is one iteration of batch descent."""
    from .operators.descent import Config

    src = s.readStream.schema(s.read.parquet(f"{sf}/events.parquet").schema).parquet(f"{sf}/event*.parquet")
    w = streams.stream_fit(tasks.transform_columns(src, "event_id", tasks.W6.label, tasks.W6.features), 3, "hinge", Config(), _folder(s, "ckpt"), _folder(s, "models"))
    return s.createDataFrame([tuple(round(float(x), 6) + 0.0 for x in w)], "w0 double, w1 double, w2 double")


add("stream_sgd", _stream_sgd, f"SELECT round(avg(label*x0), 6) AS w0, round(avg(label*x1), 6) AS w1, round(avg(label*x2), 6) AS w2 FROM ({tasks.W6.sql()})")
add("stream_stateful_weights", lambda s, sf: streams.replay(s, sf, lambda e: streams.per_user_models(e, "logistic", __import__("descent_planner.operators.descent", fromlist=["Config"]).Config()), _folder(s, "ckpt"), mode="update"))


def _late(s, sf):
    e = t(s, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    late = F.col("event_id") % 20 == 0
    return _text(streams.late_counts(s, e.where(~late), e.where(late), _folder(s, "late")))


_MARKS = "SELECT date_trunc('millisecond', max(ts) FILTER (event_id % 20 <> 0)) - INTERVAL 1 HOUR AS w1, date_trunc('millisecond', max(ts)) - INTERVAL 1 HOUR AS w2 FROM events"
add("stream_late_data", _late, f"SELECT {_DAY.format(w='d')}, CASE WHEN d + INTERVAL 1 DAY <= w1 THEN on_time ELSE n END AS n FROM (SELECT date_trunc('day', ts) AS d, count(*) AS n, count(*) FILTER (event_id % 20 <> 0) AS on_time FROM events GROUP BY 1), ({_MARKS}) WHERE d + INTERVAL 1 DAY <= greatest(w1, w2)")
add("stream_stream_interval_join", lambda s, sf: streams.replay(s, sf, streams.followed_within, _folder(s, "ckpt"), mode="append"), "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
