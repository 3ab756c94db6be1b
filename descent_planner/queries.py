"""Queries over the methods, and the SQL that an oracle runs on the same tables.

Descent oracles are recursive queries whose state is the weight vector: one recursion step averages the gradient over
all units, or over the units that the sampler's hash picks.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.gradients import GRADIENTS
from .functions.steps import STEP_SQL, theoretical_bound
from .operators import baselines, descent, metrics, samplers
from .operators.descent import Config
from .plans import cost, estimate, language, optimizer, space
from .sources import tasks
from .sources.folders import new_folder as _folder
from .sources.models import model_frame
from .sources.tasks import W1, W2, W2_SVM, W6, W7, W8

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def _rounded(names: list[str], digits: int = 6) -> str:
    return ", ".join(f"round({n}, {digits}) + 0.0 AS {n}" for n in names)


def descent_sql(units: str, d: int, gradient: str, iters: int, step: str = "inv_sqrt", beta: float = 1.0, norm: str = "l1", where: str = "true", extra: str = "", source: str = "u", reg: str = "", cols: str | None = None, tolerance: float | None = None, digits: int = 6) -> str:
    """A recursive query for ``iters`` iterations; ``where`` restricts the units of iteration t.i + 1."""
    w = [f"w{j}" for j in range(d)]
    z = "(" + "+".join(f"t.w{j}*u.x{j}" for j in range(d)) + ")"
    c = GRADIENTS[gradient].sql.format(z=z, y="u.label")
    a = STEP_SQL[step].format(b=f"{beta}::DOUBLE", i="(t.i+1)")
    diff = [f"abs(n{j}-o{j})" for j in range(d)]
    delta = {"l1": "+".join(diff), "l2": "sqrt(" + "+".join(f"{x}*{x}" for x in diff) + ")", "linf": f"greatest({', '.join(diff)})"}[norm]
    new = ", ".join(f"t.w{j} - ({a})*(avg(({c})*u.x{j}){reg.format(w=f't.w{j}')}) AS n{j}, t.w{j} AS o{j}" for j in range(d))
    go_on = f" AND (t.delta IS NULL OR t.delta >= {tolerance})" if tolerance is not None else ""
    return f"""
WITH RECURSIVE u AS MATERIALIZED ({units}){extra},
t AS (
  SELECT 0 AS i, {", ".join(f"0.0::DOUBLE AS {x}" for x in w)}, NULL::DOUBLE AS delta, 0::BIGINT AS n_used
  UNION ALL
  SELECT i, {", ".join(f"n{j}" for j in range(d))}, {delta}, n FROM (
    SELECT t.i + 1 AS i, {new}, count(*) AS n
    FROM t, {source} WHERE t.i < {iters}{go_on} AND {where}
    GROUP BY t.i, {", ".join(f"t.{x}" for x in w)}))
SELECT i AS iter, {_rounded(w, digits)}, {cols or f"round(delta, {digits}) + 0.0 AS delta"} FROM t WHERE i > 0"""


def trace(spark: SparkSession, fit: descent.FitResult, delta: bool = True, used: bool = False, last: bool = False, digits: int = 6) -> DataFrame:
    d = len(fit.weights)
    r6 = lambda x: round(float(x), digits) + 0.0
    rows = [(r["iter"], *(r6(x) for x in r["w"]), *([None if r["delta"] is None else r6(r["delta"])] * delta), *([r["n_used"]] * used)) for r in fit.trace]
    return spark.createDataFrame(rows[-1:] if last else rows, "iter int, " + ", ".join(f"w{j} double" for j in range(d)) + ", delta double" * delta + ", n_used long" * used)


# --- units, statistics, gradients and losses -----------------------------------------------------------------------

for _name, _task in (("units_charge", W1), ("units_big_charge", W2), ("units_event_heavy", W6), ("units_part_price", W7)):
    QUERIES[_name] = lambda spark, sf, t=_task: t.units(spark, sf).select("unit_id", "label", *(F.round(F.element_at("features", j + 1), 6).alias(f"x{j}") for j in range(t.dim)))
    ORACLES[_name] = f"SELECT unit_id, label, {', '.join(f'round(x{j}, 6) AS x{j}' for j in range(_task.dim))} FROM ({_task.sql()})"

_HALF_SQL = "SELECT vec_id AS unit_id, CASE WHEN list_sum(list_transform(range(1, 65), lambda j: cos(j-1)*embedding[j]::DOUBLE)) > 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, " + ", ".join(f"embedding[{j + 1}]::DOUBLE AS x{j}" for j in range(64)) + " FROM embeddings"


@query("units_halfspace", f"SELECT unit_id, label, round(x0, 6) AS x0, round(x63, 6) AS x63 FROM ({_HALF_SQL})")
def _(spark, sf):
    return tasks.halfspace(spark, sf).select("unit_id", "label", F.round(F.col("features")[0], 6).alias("x0"), F.round(F.col("features")[63], 6).alias("x63"))


_WORDS_SQL = "SELECT DISTINCT doc_id AS unit_id, (('0x'||substr(md5(w),1,8))::BIGINT % 1024)::INT AS bucket FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[ \n\t]+')) AS w FROM documents) WHERE w <> ''"
query("units_doc_sparse", _WORDS_SQL)(lambda spark, sf: tasks.doc_words(spark, sf))
query("units_doc_quality", f"SELECT unit_id, (2.0*quality-1)::DOUBLE AS label, (count(*)+1)::BIGINT AS n_features, round(ln(1+any_value(n_chars))/10, 6) AS last_value FROM ({_WORDS_SQL}) b JOIN labels l ON b.unit_id = l.doc_id JOIN documents d ON b.unit_id = d.doc_id GROUP BY unit_id, quality")(
    lambda spark, sf: tasks.doc_quality(spark, sf).select("unit_id", "label", F.size("idx").cast("long").alias("n_features"), F.round(F.element_at("val", -1), 6).alias("last_value"))
)
_STAT_COLS = ["l_quantity", "l_discount", "l_tax"]


@query("stage_stats_lineitem", "SELECT count(*) AS n, " + ", ".join(f"round(avg({c}),6) AS mean_{c}, round(stddev_pop({c}),6) AS std_{c}, min({c}) AS min_{c}, max({c}) AS max_{c}" for c in _STAT_COLS) + " FROM lineitem")
def _(spark, sf):
    s = descent.stage_stats(tasks.table(spark, sf, "lineitem"), _STAT_COLS)
    return spark.createDataFrame([{k: round(v, 6) if k[:3] in ("mea", "std") else v for k, v in s.items()}])


@query("transform_standardized", "SELECT o_orderkey, round((o_totalprice - avg(o_totalprice) OVER ()) / stddev_pop(o_totalprice) OVER (), 6) + 0.0 AS z FROM orders")
def _(spark, sf):
    o = tasks.table(spark, sf, "orders")
    s = descent.stage_stats(o, ["o_totalprice"])
    return o.select("o_orderkey", (F.round(descent.standardised(["o_totalprice"], s)[0], 6) + 0.0).alias("z"))


_FIXED = {"linear": (W1, [0.1, 0.2, 0.3, -0.1]), "logistic": (W2, [0.1, -0.2, 0.3, 0.05]), "hinge": (W6, [0.2, -0.3, 0.1])}


def _z(w) -> str:
    return "(" + "+".join(f"({v}::DOUBLE)*x{j}" for j, v in enumerate(w)) + ")"


for _g, (_task, _w) in _FIXED.items():

    def _gradient(spark, sf, g=_g, t=_task, w=_w, reg="none", lam=0.0):
        p = descent.compute(t.units(spark, sf), np.array(w), GRADIENTS[g])
        extra = descent.regulariser(reg, lam, np.array(w)) * p.n
        return spark.createDataFrame([(p.n, *(round(float(x), 4) + 0.0 for x in p.grad + extra))], "n long, " + ", ".join(f"g{j} double" for j in range(len(w))))

    _c = GRADIENTS[_g].sql.format(z=_z(_w), y="label")
    QUERIES[f"gradient_{_g}_fixed_w"] = _gradient
    ORACLES[f"gradient_{_g}_fixed_w"] = f"SELECT count(*) AS n, {', '.join(f'round(sum(({_c})*x{j}), 4) + 0.0 AS g{j}' for j in range(len(_w)))} FROM ({_task.sql()})"
    if _g == "logistic":
        for _r in ("l1", "l2"):
            QUERIES[f"gradient_regularized_{_r}"] = lambda spark, sf, f=_gradient, r=_r: f(spark, sf, reg=r, lam=0.01)
            _e = [f"+ count(*)*0.01*({'sign(' if _r == 'l1' else '('}{v}::DOUBLE))" for v in _w]
            ORACLES[f"gradient_regularized_{_r}"] = f"SELECT count(*) AS n, {', '.join(f'round(sum(({_c})*x{j}) {_e[j]}, 4) + 0.0 AS g{j}' for j in range(len(_w)))} FROM ({_task.sql()})"
    QUERIES[f"loss_{_g}_fixed_w"] = lambda spark, sf, g=_g, t=_task, w=_w: spark.createDataFrame([(round(descent.objective(t.units(spark, sf), np.array(w), g), 6),)], "objective double")
    ORACLES[f"loss_{_g}_fixed_w"] = f"SELECT round(avg({GRADIENTS[_g].sql_loss.format(z=_z(_w), y='label')}), 6) AS objective FROM ({_task.sql()})"


_SPARSE_GRADIENT_SQL = f"WITH b AS ({_WORDS_SQL}), s AS (SELECT unit_id, 1/sqrt(count(*)) AS v FROM b GROUP BY unit_id) SELECT bucket AS j, round(sum(-(CASE WHEN lang='en' THEN 1.0 ELSE -1.0 END)*0.5*v), 5) + 0.0 AS g FROM b JOIN s USING (unit_id) JOIN documents d ON d.doc_id = b.unit_id GROUP BY bucket"


@query("gradient_sparse_keyed", _SPARSE_GRADIENT_SQL)
def _(spark, sf):
    """The logistic gradient of hashed texts at zero weights, margins by a join with the table of weights."""
    weights = spark.range(1024).select(F.col("id").cast("int").alias("j"), F.lit(0.0).alias("w"))
    out = descent.sparse_gradient(descent.sparse_margins(tasks.doc_language(spark, sf), weights), GRADIENTS["logistic"])
    return out.select("j", (F.round("g", 5) + 0.0).alias("g"))


@query("gradient_sparse_partials", _SPARSE_GRADIENT_SQL)
def _(spark, sf):
    """The same with the weights in every task and partial sums."""
    return descent.sparse_partials(tasks.doc_language(spark, sf), np.zeros(1024), GRADIENTS["logistic"]).select("j", (F.round("g", 5) + 0.0).alias("g"))


# --- batch descent ---------------------------------------------------------------------------------------------------

_FIX = Config(tolerance=0.0, max_iter=10)


def _fixed(iters: int, **changes) -> Config:
    return descent.with_tolerance(_FIX, max_iter=iters, **changes)


for _name, _task, _g, _n, _b in (("bgd_linear", W1, "linear", 10, 0.3), ("bgd_logistic", W2, "logistic", 8, 1.0), ("bgd_hinge", W6, "hinge", 8, 1.0), ("bgd_part_price_exact", W7, "linear", 15, 0.5), ("bgd_return_flag", W8, "logistic", 6, 1.0)):
    QUERIES[_name] = lambda spark, sf, t=_task, g=_g, n=_n, b=_b: trace(spark, descent.bgd(t.units(spark, sf), g, _fixed(n, beta=b)))
    ORACLES[_name] = descent_sql(_task.sql(), _task.dim, _g, _n, beta=_b)
for _s, _key in (("constant", "const"), ("inv_sqrt", "inv_sqrt"), ("inv", "inv"), ("inv_sq", "inv_sq")):
    QUERIES[f"bgd_step_{_key}"] = lambda spark, sf, s=_s: trace(spark, descent.bgd(W7.units(spark, sf), "linear", _fixed(8, beta=0.3, step=s)))
    ORACLES[f"bgd_step_{_key}"] = descent_sql(W7.sql(), 2, "linear", 8, _s, 0.3)
for _s in ("l1", "l2", "linf"):
    QUERIES[f"bgd_norm_{_s}"] = lambda spark, sf, s=_s: trace(spark, descent.bgd(W7.units(spark, sf), "linear", _fixed(6, beta=0.3, norm=s)))
    ORACLES[f"bgd_norm_{_s}"] = descent_sql(W7.sql(), 2, "linear", 6, "inv_sqrt", 0.3, _s)
for _r, _sql in (("l1", "+0.01*sign({w})"), ("l2", "+0.01*{w}")):
    QUERIES[f"bgd_regularized_{_r}"] = lambda spark, sf, r=_r: trace(spark, descent.bgd(W6.units(spark, sf), "logistic", _fixed(6, reg=r, lam=0.01)))
    ORACLES[f"bgd_regularized_{_r}"] = descent_sql(W6.sql(), 3, "logistic", 6, reg=_sql)


@query("bgd_to_tolerance", descent_sql(W7.sql(), 2, "linear", 200, beta=0.5, tolerance=0.02) + " ORDER BY i DESC LIMIT 1")
def _(spark, sf):
    return trace(spark, descent.bgd(W7.units(spark, sf), "linear", Config(beta=0.5, tolerance=0.02, max_iter=200)), last=True)


_H_SQL = """WITH RECURSIVE u AS MATERIALIZED (SELECT label, f FROM (SELECT CASE WHEN list_sum(list_transform(range(1, 65), lambda j: cos(j-1)*embedding[j]::DOUBLE)) > 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, embedding::DOUBLE[] AS f FROM embeddings)),
t AS (
  SELECT 0 AS i, list_transform(range(1, 65), lambda j: 0.0::DOUBLE) AS w
  UNION ALL
  SELECT i + 1, list(v ORDER BY j) FROM (
    SELECT t.i, j, any_value(t.w[j]) - avg(CASE WHEN label*list_dot_product(t.w, f) < 1 THEN -label ELSE 0.0 END * f[j]) / sqrt(t.i + 1) AS v
    FROM t, u, range(1, 65) r(j) WHERE t.i < 10 GROUP BY t.i, j) GROUP BY i)
SELECT (j - 1)::INT AS dim, round(w[j], 6) + 0.0 AS weight FROM t, range(1, 65) r(j) WHERE i = 10"""


@query("bgd_halfspace_64", _H_SQL)
def _(spark, sf):
    fit = descent.bgd(tasks.halfspace(spark, sf), "hinge", _fixed(10))
    return spark.createDataFrame([(j, round(float(x), 6) + 0.0) for j, x in enumerate(fit.weights)], "dim int, weight double")


_SPARSE_SQL = f"""WITH RECURSIVE b AS MATERIALIZED ({_WORDS_SQL.replace('1024', '256')}),
c AS MATERIALIZED (SELECT b.unit_id, bucket, 1/sqrt(count(*) OVER (PARTITION BY b.unit_id)) AS v, CASE WHEN lang = 'en' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM b JOIN documents d ON d.doc_id = b.unit_id),
t AS (
  SELECT 0 AS i, range::INT AS j, 0.0::DOUBLE AS w FROM range(256)
  UNION ALL
  SELECT t.i + 1, t.j, t.w - coalesce(g.g, 0.0) / (SELECT count(DISTINCT unit_id) FROM c) / sqrt(t.i + 1)
  FROM t LEFT JOIN (
    SELECT c.bucket AS j, sum(-z.y/(1+exp(greatest(-700.0, least(700.0, z.y*z.z))))*c.v) AS g
    FROM (SELECT c.unit_id, c.y, sum(t.w*c.v) AS z FROM t JOIN c ON c.bucket = t.j GROUP BY c.unit_id, c.y) z JOIN c USING (unit_id)
    GROUP BY c.bucket) g USING (j)
  WHERE t.i < 3)
SELECT j, round(w, 6) + 0.0 AS weight FROM t WHERE i = 3"""


@query("bgd_sparse_language", _SPARSE_SQL)
def _(spark, sf):
    fit = descent.bgd_sparse(tasks.doc_language(spark, sf, 256), "logistic", _fixed(3), 256)
    return spark.createDataFrame([(j, round(float(x), 6) + 0.0) for j, x in enumerate(fit.weights)], "j int, weight double")


# --- samplers and stochastic descent ---------------------------------------------------------------------------------

SEED, PARTS, BATCH = 7, 8, 100


def _laid(spark, sf) -> DataFrame:
    return samplers.with_parts(W6.units(spark, sf), PARTS)


_U6 = f"SELECT *, (unit_id % {PARTS})::INT AS part_id FROM ({W6.sql()})"


def _rank(draw, unit) -> str:
    return samplers.rank_sql(SEED, draw, unit)


def _batches_sql(m: int) -> str:
    """b(i, unit_id): the batches of the shuffled partitions of the first epoch."""
    return f""",
p AS (SELECT part_id, count(*) // {m} AS k, row_number() OVER (ORDER BY {_rank(0, "'part'||part_id")}, part_id) AS po FROM u GROUP BY part_id),
q AS (SELECT part_id, k, coalesce(sum(k) OVER (ORDER BY po ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM p),
s AS (SELECT u.*, (row_number() OVER (PARTITION BY part_id ORDER BY {_rank(0, "unit_id")}, unit_id) - 1) AS rn FROM u),
b AS (SELECT (before + rn // {m} + 1)::BIGINT AS i, s.* FROM s JOIN q USING (part_id) WHERE rn // {m} < k)"""


def _picks_sql(m: int, iters: int, weight: str = "count(*)") -> str:
    """b(i, ...): units drawn by random partitions, in proportion to their ``weight``, with replacement."""
    return f""",
p AS (SELECT part_id, count(*) AS n, {weight} AS g FROM u GROUP BY part_id),
c AS (SELECT part_id, n, sum(g) OVER (ORDER BY part_id) / (SELECT sum(g) FROM p)::DOUBLE AS high, coalesce(sum(g) OVER (ORDER BY part_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / (SELECT sum(g) FROM p)::DOUBLE AS low FROM p),
d AS (SELECT i, k, {_rank("i", "'p'||k")} / 4294967296.0::DOUBLE AS a, {_rank("i", "'u'||k")} AS v FROM range(1, {iters + 1}) x(i), range({m}) y(k)),
s AS (SELECT u.*, row_number() OVER (PARTITION BY part_id ORDER BY unit_id) - 1 AS rn FROM u),
b AS (SELECT d.i, s.* FROM d JOIN c ON d.a >= c.low AND d.a < c.high JOIN s ON s.part_id = c.part_id AND s.rn = (d.v::HUGEINT * c.n) // 4294967296)"""


def _joined(name: str, algorithm: str, extra: str, iters: int, run) -> None:
    # a hinge batch is summed in another order there, which may cross the edge of a sixth digit; a single unit isn't
    digits = 4 if algorithm == "mgd" else 6
    QUERIES[name] = lambda spark, sf: trace(spark, run(_laid(spark, sf)), used=True, digits=digits)
    ORACLES[name] = descent_sql(_U6, 3, "hinge", iters, extra=extra, source="b u", where="u.i = t.i + 1", cols=f"round(delta, {digits}) + 0.0 AS delta, n_used", digits=digits)


QUERIES["mgd_bernoulli_hash"] = lambda spark, sf: trace(spark, descent.mgd(W6.units(spark, sf), "hinge", _fixed(6), fraction=0.1), used=True)
ORACLES["mgd_bernoulli_hash"] = descent_sql(W6.sql(), 3, "hinge", 6, where=f"{_rank('t.i + 1', 'u.unit_id')} < 0.1::DOUBLE * 4294967296", cols="round(delta, 6) + 0.0 AS delta, n_used")
_joined("mgd_shuffled_partition_hash", "mgd", _batches_sql(BATCH), 20, lambda u: descent.mgd(u, "hinge", _fixed(20), BATCH, "shuffle"))
_joined("sgd_shuffled_partition_hash", "sgd", _batches_sql(1), 30, lambda u: descent.sgd(u, "hinge", _fixed(30, beta=0.7), "shuffle"))
ORACLES["sgd_shuffled_partition_hash"] = descent_sql(_U6, 3, "hinge", 30, beta=0.7, extra=_batches_sql(1), source="b u", where="u.i = t.i + 1", cols="round(delta, 6) + 0.0 AS delta, n_used")
_joined("mgd_random_partition_hash", "mgd", _picks_sql(20, 6), 6, lambda u: descent.mgd(u, "hinge", _fixed(6), 20, "random"))
_joined("sgd_random_partition_hash", "sgd", _picks_sql(1, 8), 8, lambda u: descent.sgd(u, "hinge", _fixed(8), "random"))


@query("mgd_lazy_equals_eager", "SELECT s AS sampler, 0.0::DOUBLE AS max_difference FROM (VALUES ('random'), ('shuffle')) v(s)")
def _(spark, sf):
    raw = samplers.with_parts(tasks.table(spark, sf, "events").withColumn("unit_id", F.col("event_id")), PARTS)
    lazily = lambda df: tasks.transform_columns(df, "unit_id", W6.label, W6.features)
    rows = []
    for s in ("random", "shuffle"):
        lazy = descent.mgd(raw, "hinge", _fixed(3), 50, s, transform=lazily)
        eager = descent.mgd(_laid(spark, sf), "hinge", _fixed(3), 50, s)
        rows.append((s, float(np.abs(lazy.weights - eager.weights).max())))
    return spark.createDataFrame(rows, "sampler string, max_difference double")


@query("svrg_m1_is_bgd", descent_sql(W6.sql(), 3, "logistic", 5))
def _(spark, sf):
    return trace(spark, descent.svrg(_laid(spark, sf), "logistic", _fixed(5), 1))


def svrg_sql(units: str, d: int, gradient: str, iters: int, beta: float, every: int) -> str:
    """Variance reduction: the state holds weights w, the anchor v and its mean gradient m."""
    g = GRADIENTS[gradient].sql
    at = lambda k: g.format(z="(" + "+".join(f"t.{k}{j}*u.x{j}" for j in range(d)) + ")", y="u.label")
    over = range(d)
    a = f"({beta}::DOUBLE/sqrt(i))"
    step = [f"CASE WHEN anchor THEN f{j} ELSE f{j} - h{j} + m{j} END" for j in over]
    new = [f"w{j} - {a}*({step[j]})" for j in over]
    return f"""
WITH RECURSIVE u0 AS MATERIALIZED ({units}), u AS (SELECT * FROM u0){_batches_sql(1)},
r AS MATERIALIZED (SELECT u0.*, b.i AS k FROM u0 LEFT JOIN b USING (unit_id)),
t AS (
  SELECT 0 AS i, {", ".join(f"0.0::DOUBLE AS {k}{j}" for k in "wvm" for j in over)}, 0.0::DOUBLE AS delta, 0::BIGINT AS n_used
  UNION ALL
  SELECT i, {", ".join(new)}, {", ".join(f"CASE WHEN anchor THEN w{j} ELSE v{j} END" for j in over)}, {", ".join(f"CASE WHEN anchor THEN f{j} ELSE m{j} END" for j in over)}, {"+".join(f"abs(({new[j]}) - w{j})" for j in over)}, n FROM (
    SELECT t.i + 1 AS i, t.i % {every} = 0 AS anchor, {", ".join(f"t.{k}{j}" for k in "wvm" for j in over)}, {", ".join(f"avg(({at('w')})*u.x{j}) AS f{j}, avg(({at('v')})*u.x{j}) AS h{j}" for j in over)}, count(*) AS n
    FROM t, r u WHERE t.i < {iters} AND (t.i % {every} = 0 OR u.k = t.i - t.i // {every})
    GROUP BY t.i, {", ".join(f"t.{k}{j}" for k in "wvm" for j in over)}))
SELECT i AS iter, {_rounded([f"w{j}" for j in over], 5)}, round(delta, 5) + 0.0 AS delta, n_used FROM t WHERE i > 0"""


def line_search_sql(task, gradient: str, iters: int, rule: str, beta: float = 1.0, shrink: float = 0.5, trials: int = 12, sigma: float = 1e-4) -> str:
    """Mean losses of all trial steps of an iteration at once; the first step that passes is taken."""
    d, g = task.dim, GRADIENTS[gradient]
    over = range(d)
    z = "(" + "+".join(f"t.w{j}*u.x{j}" for j in over) + ")"
    ahead = "(" + "+".join(f"(s.w{j}-k.a*s.g{j})*u.x{j}" for j in over) + ")"
    square = "+".join(f"g{j}*g{j}" for j in over)
    ok = f"f0 - f >= {sigma}*a*({square})" if rule == "armijo" else "f0 - f < a*i"
    alpha = f"{beta}::DOUBLE*pow({shrink}, coalesce(first_ok, {trials - 1}))"
    if rule == "armijo":
        alpha = f"CASE WHEN first_ok IS NULL AND last_drop < 0 THEN 0.0 ELSE {alpha} END"
    keep = ", ".join(f"{k}{j}" for k in "wg" for j in over)
    return f"""
WITH RECURSIVE u AS MATERIALIZED ({task.sql()}),
k AS (SELECT x AS k, {beta}::DOUBLE*pow({shrink}, x) AS a FROM range({trials}) r(x)),
t AS (
  SELECT 0 AS i, {", ".join(f"0.0::DOUBLE AS w{j}" for j in over)}, 0.0::DOUBLE AS step, 0.0::DOUBLE AS delta
  UNION ALL
  SELECT i, {", ".join(f"w{j} - step*g{j}" for j in over)}, step, {"+".join(f"abs(step*g{j})" for j in over)} FROM (
    SELECT i, {keep}, {alpha} AS step FROM (
      SELECT i, {keep}, min(k) FILTER ({ok}) AS first_ok, max(f0 - f) FILTER (k = {trials - 1}) AS last_drop FROM (
        SELECT s.i, {", ".join(f"s.{k}{j}" for k in "wg" for j in over)}, s.f0, k.k, k.a, avg({g.sql_loss.format(z=ahead, y="u.label")}) AS f
        FROM (SELECT t.i + 1 AS i, {", ".join(f"t.w{j}" for j in over)}, {", ".join(f"avg(({g.sql.format(z=z, y='u.label')})*u.x{j}) AS g{j}" for j in over)}, avg({g.sql_loss.format(z=z, y="u.label")}) AS f0
              FROM t, u WHERE t.i < {iters} GROUP BY t.i, {", ".join(f"t.w{j}" for j in over)}) s, k, u
        GROUP BY s.i, {", ".join(f"s.{k}{j}" for k in "wg" for j in over)}, s.f0, k.k, k.a)
      GROUP BY i, {keep})))
SELECT i AS iter, round(step, 9) AS step, round(delta, 5) + 0.0 AS delta FROM t WHERE i > 0"""


def secant_sql(task, gradient: str, iters: int, beta: float, kind: int) -> str:
    """Steps from the last two weights and gradients: the state holds weights w and the last ones v with their gradient m."""
    d, g = task.dim, GRADIENTS[gradient]
    over = range(d)
    z = "(" + "+".join(f"t.w{j}*u.x{j}" for j in over) + ")"
    dot = lambda x, y: "(" + "+".join(f"({x.format(j=j)})*({y.format(j=j)})" for j in over) + ")"
    s_, y_ = "w{j}-v{j}", "g{j}-m{j}"
    top, low = (dot(s_, s_), dot(s_, y_)) if kind == 1 else (dot(s_, y_), dot(y_, y_))
    keep = ", ".join(f"t.{k}{j}" for k in "wvm" for j in over)
    return f"""
WITH RECURSIVE u AS MATERIALIZED ({task.sql()}),
t AS (
  SELECT 0 AS i, {", ".join(f"0.0::DOUBLE AS {k}{j}" for k in "wvm" for j in over)}, 0.0::DOUBLE AS step, 0.0::DOUBLE AS delta
  UNION ALL
  SELECT i, {", ".join(f"w{j} - step*g{j}" for j in over)}, {", ".join(f"w{j}" for j in over)}, {", ".join(f"g{j}" for j in over)}, step, {"+".join(f"abs(step*g{j})" for j in over)} FROM (
    SELECT *, CASE WHEN i > 1 AND {low} > 0 AND {top} > 0 THEN {top} / {low} ELSE {beta}::DOUBLE/sqrt(i) END AS step FROM (
      SELECT t.i + 1 AS i, {keep}, {", ".join(f"avg(({g.sql.format(z=z, y='u.label')})*u.x{j}) AS g{j}" for j in over)}
      FROM t, u WHERE t.i < {iters} GROUP BY t.i, {keep})))
SELECT i AS iter, round(step, 5) AS step, round(delta, 5) + 0.0 AS delta FROM t WHERE i > 0"""


def _steps(spark: SparkSession, fit: descent.FitResult, step_digits: int) -> DataFrame:
    return spark.createDataFrame([(r["iter"], round(r["step"], step_digits), round(r["delta"], 5) + 0.0) for r in fit.trace], "iter int, step double, delta double")


query("svrg_trace", svrg_sql(_U6, 3, "logistic", 12, 0.3, 5))(lambda spark, sf: trace(spark, descent.svrg(_laid(spark, sf), "logistic", _fixed(12, beta=0.3), 5), used=True, digits=5))
query("line_search_armijo", line_search_sql(W1, "linear", 6, "armijo"))(lambda spark, sf: _steps(spark, descent.bgd_line_search(W1.units(spark, sf), "linear", _fixed(6)), 9))
query("line_search_printed", line_search_sql(W1, "linear", 4, "printed"))(lambda spark, sf: _steps(spark, descent.bgd_line_search(W1.units(spark, sf), "linear", _fixed(4), rule="printed"), 9))
for _kind in (1, 2):
    query("bb_step_trace" if _kind == 1 else "bb2_step_trace", secant_sql(W1, "linear", 8, 0.3, _kind))(lambda spark, sf, k=_kind: _steps(spark, descent.bgd_bb(W1.units(spark, sf), "linear", _fixed(8, beta=0.3), k), 5))
_joined("mgd_random_uniform_weights", "mgd", _picks_sql(20, 4, "1"), 4, lambda u: descent.mgd(u, "hinge", _fixed(4), 20, "random", weights="uniform"))


@query("sample_bernoulli_hash", " UNION ALL ".join(f"SELECT {i} AS iter, count(*) AS n FROM events WHERE {_rank(i, 'event_id')} < 0.1::DOUBLE * 4294967296" for i in (1, 2, 3)))
def _(spark, sf):
    u = tasks.table(spark, sf, "events").select(F.col("event_id").alias("unit_id"))
    b = samplers.Bernoulli(0.1)
    # one scan for all draws
    row = u.agg(*(F.count(F.when(b.condition(i, F.col("unit_id")), 1)) for i in (1, 2, 3))).first()
    return spark.createDataFrame([(i + 1, n) for i, n in enumerate(row)], "iter int, n long")


@query("sample_boosted_fraction", "SELECT n, round(1 - pow(0.001, 1.0::DOUBLE/n), 9) AS fraction FROM (SELECT count(*) AS n FROM events)")
def _(spark, sf):
    n = tasks.table(spark, sf, "events").count()
    return spark.createDataFrame([(n, round(samplers.boosted_fraction(n), 9))], "n long, fraction double")


@query("sample_random_partition", f"WITH u AS ({_U6}){_picks_sql(20, 4)} SELECT i::INT AS iter, unit_id FROM b")
def _(spark, sf):
    u = _laid(spark, sf)
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(u).collect()}
    s = samplers.RandomPartition(sizes, 20, SEED)
    out = [s.draw(u, i).select(F.lit(i).alias("iter"), "unit_id") for i in range(1, 5)]
    return out[0].union(out[1]).union(out[2]).union(out[3])


@query("sample_shuffled_partition_slices", f"WITH u AS ({_U6}){_batches_sql(BATCH)} SELECT i::INT AS iter, unit_id, part_id FROM b WHERE i <= 30")
def _(spark, sf):
    u = _laid(spark, sf)
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(u).collect()}
    s = samplers.ShuffledPartition(sizes, BATCH, SEED)
    return spark.createDataFrame([(i, r.unit_id, p) for i in range(1, 31) for p, r in s.draw_rows(u)], "iter int, unit_id long, part_id int")


_MIXED = f"""WITH u AS ({_U6}),
e AS (SELECT x AS epoch FROM range(3) r(x)),
p AS (SELECT epoch, part_id, count(*) AS n, (row_number() OVER (PARTITION BY epoch ORDER BY {_rank("epoch", "'part'||part_id")}, part_id) - 1) // 2 AS g FROM u, e GROUP BY epoch, part_id),
h AS (SELECT epoch, g, sum(n) // {BATCH} AS k, coalesce(sum(sum(n) // {BATCH}) OVER (ORDER BY epoch, g ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM p GROUP BY epoch, g),
s AS (SELECT unit_id, part_id, epoch, g, (row_number() OVER (PARTITION BY epoch, part_id ORDER BY {_rank("epoch", "unit_id")}, unit_id) - 0.5::DOUBLE) / n AS place FROM u JOIN p USING (part_id)),
r AS (SELECT *, row_number() OVER (PARTITION BY epoch, g ORDER BY place, part_id) - 1 AS rn FROM s)
SELECT (before + rn // {BATCH} + 1)::INT AS iter, unit_id, part_id FROM r JOIN h USING (epoch, g) WHERE rn // {BATCH} < k AND before + rn // {BATCH} < 24"""


@query("sample_mixed_partition_slices", _MIXED)
def _(spark, sf):
    """Batches of which each takes its units from two partitions, the next two being read in the background."""
    u = _laid(spark, sf)
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(u).collect()}
    s = samplers.ShuffledPartition(sizes, BATCH, SEED, mix=2, prefetch=True)
    rows = [(i, r.unit_id, p) for i in range(1, 25) for p, r in s.draw_rows(u)]
    s.close()
    return spark.createDataFrame(rows, "iter int, unit_id long, part_id int")


query("sample_speculation_1000", f"SELECT o_orderkey AS unit_id FROM orders ORDER BY {_rank(0, 'o_orderkey')}, o_orderkey LIMIT 1000")(lambda spark, sf: samplers.draw_once(tasks.table(spark, sf, "orders").select(F.col("o_orderkey").alias("unit_id")), 1000).select("unit_id"))
query("partition_catalog", f"SELECT (event_id % {PARTS})::INT AS part_id, count(*) AS n_units FROM events GROUP BY 1")(lambda spark, sf: samplers.partition_catalog(_laid(spark, sf)))


@query("scan_partition_pruned", f"SELECT unit_id, label FROM ({W6.sql()}) WHERE unit_id % {PARTS} = 3")
def _(spark, sf):
    path = _folder(spark, "layout")
    return samplers.layout_partitions(W6.units(spark, sf), path, PARTS).where("part_id = 3").select("unit_id", "label")


@query("layout_catalog_sizes", f"SELECT (event_id % {PARTS})::INT AS part_id, count(*) AS n_units FROM events GROUP BY 1")
def _(spark, sf):
    sizes = samplers.lay_out(W6.units(spark, sf), _folder(spark, "layout"), PARTS).sizes
    return spark.createDataFrame(list(sizes.items()), "part_id int, n_units long")


def _over_layout(sampler: str, batch: int, iters: int):
    """As the hash oracles, with the partitions in files; slices of a partition give the same batches."""
    options = {"slice_units": 500} if sampler == "shuffle" else {}
    return lambda spark, sf: trace(spark, descent.mgd(None, "hinge", _fixed(iters), batch, sampler, layout=samplers.lay_out(W6.units(spark, sf), _folder(spark, "layout"), PARTS), **options), used=True, digits=4)


for _key, _sampler, _m, _n, _like in (("shuffled", "shuffle", BATCH, 20, "mgd_shuffled_partition_hash"), ("random", "random", 20, 6, "mgd_random_partition_hash")):
    QUERIES[f"mgd_layout_{_key}"] = _over_layout(_sampler, _m, _n)
    ORACLES[f"mgd_layout_{_key}"] = ORACLES[_like]


# --- speculation, curves, cost and choice ----------------------------------------------------------------------------

_SAMPLE_SQL = f"SELECT * FROM ({W7.sql()}) ORDER BY {_rank(0, 'unit_id')}, unit_id LIMIT 1000"


def _pairs(spark, sf):
    return estimate.speculate(W7.units(spark, sf), "linear", Config(beta=0.5), ("bgd",), eps_s=0.05)["bgd"].pairs


_SPEC = descent_sql(_SAMPLE_SQL, 2, "linear", 300, beta=0.5, tolerance=0.05)
_PAIRS_SQL = f"WITH RECURSIVE{_SPEC.split('WITH RECURSIVE', 1)[1].rsplit('SELECT i AS iter', 1)[0]}, e AS (SELECT i AS iter, delta FROM t WHERE i > 0 AND delta > 0"
_PAIRS_SQL = _PAIRS_SQL.rstrip() + ")"


@query("speculation_trace_bgd", _PAIRS_SQL + " SELECT iter, round(delta, 6) AS delta FROM e")
def _(spark, sf):
    return spark.createDataFrame([(i, round(e, 6)) for e, i in _pairs(spark, sf)], "iter int, delta double")


@query("fit_inverse_a", _PAIRS_SQL + " SELECT round(sum(iter/delta)/sum(1/(delta*delta)), 5) AS a FROM e")
def _(spark, sf):
    return spark.createDataFrame([(round(estimate.fit_inverse(_pairs(spark, sf)), 5),)], "a double")


@query("estimate_iterations_grid", _PAIRS_SQL + ", f AS (SELECT sum(iter/delta)/sum(1/(delta*delta)) AS a FROM e) SELECT eps_d, greatest(1, ceil(a/eps_d))::BIGINT AS iters FROM f, (VALUES (0.01::DOUBLE), (0.001::DOUBLE), (0.0001::DOUBLE)) v(eps_d)")
def _(spark, sf):
    p = _pairs(spark, sf)
    return spark.createDataFrame([(e, estimate.estimate_iterations(p, e)[0]) for e in (0.01, 0.001, 0.0001)], "eps_d double, iters long")


@query("fit_power", _PAIRS_SQL + " SELECT round(exp(regr_intercept(ln(iter), ln(delta))), 5) AS a, round(-regr_slope(ln(iter), ln(delta)), 5) AS b FROM e")
def _(spark, sf):
    f = estimate.fit_curve(_pairs(spark, sf), "power")
    return spark.createDataFrame([(round(f["a"], 5), round(f["b"], 5))], "a double, b double")


@query("fit_geometric", _PAIRS_SQL + " SELECT round(regr_intercept(iter, ln(1/delta)), 5) AS a, round(regr_slope(iter, ln(1/delta)), 5) AS b FROM e")
def _(spark, sf):
    f = estimate.fit_curve(_pairs(spark, sf), "geometric")
    return spark.createDataFrame([(round(f["a"], 5), round(f["b"], 5))], "a double, b double")


@query("fit_step_aware", _PAIRS_SQL + " SELECT round(sum(sqrt(iter)/delta)/sum(1/(delta*delta)), 6) AS a, 0.5::DOUBLE AS q FROM e")
def _(spark, sf):
    f = estimate.fit_curve(_pairs(spark, sf), "step_aware", "inv_sqrt")
    return spark.createDataFrame([(round(f["a"], 6), f["q"])], "a double, q double")


@query("fit_log_inverse_and_tail", _PAIRS_SQL + ", r AS (SELECT *, row_number() OVER (ORDER BY iter) - 1 AS k, count(*) OVER () AS n FROM e) SELECT round(median(iter*delta), 6) AS log_a, round(sum(iter/delta) FILTER (k >= n//2) / sum(1/(delta*delta)) FILTER (k >= n//2), 5) AS tail_a FROM r")
def _(spark, sf):
    p = _pairs(spark, sf)
    return spark.createDataFrame([(round(estimate.fit_curve(p, "log_inverse")["a"], 6), round(estimate.fit_curve(p, "tail")["a"], 5))], "log_a double, tail_a double")


@query("monotone_envelope", _PAIRS_SQL + " SELECT iter, round(min(delta) OVER (ORDER BY iter ROWS UNBOUNDED PRECEDING), 6) AS delta FROM e")
def _(spark, sf):
    return spark.createDataFrame([(i, round(e, 6)) for e, i in estimate.envelope(_pairs(spark, sf))], "iter int, delta double")


@query("speculation_all")
def _(spark, sf):
    found = estimate.speculate(W2.units(spark, sf), "logistic", Config(), **estimate.PRESETS["experiment"])
    return estimate.speculation_frame(spark, found, 1e-3, 1000)


@query("curve_study")
def _(spark, sf):
    """The whole of the events runs on the driver where one partition holds it, else on the cluster."""
    units = W6.units(spark, sf)
    large = optimizer.collect_stats(units).bytes > cost.Env().partition_bytes
    return spark.createDataFrame([(r["step"], r["actual"], r["pairs"], r["inverse"], r["step_aware"], r["power"]) for r in estimate.curve_study(units, "logistic", 1e-2, cluster=large)], "step string, actual int, pairs int, inverse long, step_aware long, power long")


@query("theoretical_bound_check", "SELECT true AS holds, 86::BIGINT AS bound")
def _(spark, sf):
    """After k iterations at a step below 1/L, the loss gap of the exact linear task is at most the bound's tolerance."""
    units = W7.units(spark, sf)
    eps, alpha = 0.01, 0.48
    k = theoretical_bound(np.zeros(2), np.array([0.9, 0.1]), alpha, eps)
    fit = descent.bgd(units, "linear", Config(step="constant", beta=alpha / 2, tolerance=0, max_iter=k))
    return spark.createDataFrame([(descent.objective(units, fit.weights, "linear") <= eps, k)], "holds boolean, bound long")


_GRID = [(n, b * 2**20, c, m, t) for n in (1000, 100_000, 88_268_800) for b in (64, 700, 5120, 163_840) for c in (8, 20) for m in (1, 1000) for t in (10, 1000)]
_GRID_SQL = "(VALUES " + ", ".join(f"({n}::DOUBLE, {b}::DOUBLE, {c}::DOUBLE, {m}::DOUBLE, {t}::DOUBLE)" for n, b, c, m, t in _GRID) + ") g(n, b, slots, m, t)"
_S = float(128 * 2**20)

#: Sets as large as the events of each type, once and in copies: the grid of the costs that are asked of given tables.
_COPIES, _SLOTS, _BATCHES, _TIMES = (1, 1000, 100_000), (8, 20), (1, 1000), (10, 1000)
#: Bytes of an event beside its properties: id, value and user.
_FIXED_BYTES = 24


def _doubles(values, name: str) -> str:
    return "(VALUES " + ", ".join(f"({v}::DOUBLE)" for v in values) + f") v_{name}({name})"


_MEASURED_SQL = f"""(SELECT s.n*copies AS n, s.b*copies AS b, slots, m, t
  FROM (SELECT count(*)::DOUBLE AS n, ({_FIXED_BYTES}*count(*) + coalesce(sum(strlen(props)), 0))::DOUBLE AS b FROM events GROUP BY event_type) s,
  {_doubles(_COPIES, "copies")}, {_doubles(_SLOTS, "slots")}, {_doubles(_BATCHES, "m")}, {_doubles(_TIMES, "t")}) g"""


def _measured_grid(spark, sf) -> list[tuple]:
    found = tasks.table(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("props")), F.lit(0)).alias("b")).collect()
    return [(r.n * k, (r.b + _FIXED_BYTES * r.n) * k, c, m, t) for r in found for k in _COPIES for c in _SLOTS for m in _BATCHES for t in _TIMES]


def _part_sql(mode: str, grid: str = _GRID_SQL) -> str:
    tail = f"greatest(0.0, b/{_S} - slots*full_waves)" if mode == "corrected" else "CASE WHEN full_waves = 0 THEN n/k ELSE fmod(n, k*slots*full_waves)/k END"
    e = cost.Env()
    share = f"least(1.0, {e.cache_bytes}/b)"
    page = f"({share}*{e.page_memory} + (1-{share})*{e.page})"
    pages = _S / e.page_bytes
    last = f"({e.seek} + least(tail, 1)*k*(b/n)/{e.page_bytes}*page)"
    if mode == "corrected":
        last = f"CASE WHEN tail > 0 THEN {last} ELSE 0 END"
    net = f"b/{e.packet_bytes}*{e.net}" + (f"*{e.packet_bytes}" if mode == "corrected" else "")
    return f"""(SELECT *, full_waves*({e.seek} + {pages}*page) + {last} AS io, (full_waves*k + ceil(least(tail, 1)*k))*{e.cpu['compute']} AS cpu, {net} AS net
  FROM (SELECT *, {tail} AS tail FROM (SELECT *, ceil(b/{_S}) AS p, ceil(b/{_S})/slots AS w, floor(ceil(b/{_S})/slots) AS full_waves, ceil(n*{_S}/b) AS k, {page} AS page FROM {grid})))"""


def _cost_rows(mode: str, grid: list[tuple] = _GRID):
    for n, b, c, m, t in grid:
        e = cost.Env(slots=c)
        data = cost.Data(n, b)
        p = cost.n_partitions(b, _S)
        yield (float(n), float(b), float(c), float(m), float(t)), {"partitions": float(p), "waves": p / c, "tail": cost.tail_partitions(n, b, _S, c, mode), "io": cost.io_cost(data, e, mode), "cpu": cost.cpu_cost(data, "compute", e, mode), "network": cost.net_cost(b, e, mode), "operator": cost.operator_cost("update", data, e, mode)}


_COST_SQL = {"partitions": "p", "waves": "w", "tail": "tail", "io": "io", "cpu": "cpu", "network": "net", "operator": "io + cpu + net"}
for _mode in ("printed", "corrected"):
    for _part, _sql in _COST_SQL.items():
        # the waves and tails of a fixed grid, the costs of what events hold; a byte sent costs 1e-8, so that the seventh
        # digit would be a tie of every other size
        _fixed_grid, _digits = _part in ("waves", "tail"), 8 if _part == "network" else 7
        QUERIES[f"cost_{_part}_{_mode}"] = lambda spark, sf, p=_part, mode=_mode, fixed=_fixed_grid, digits=_digits: spark.createDataFrame([(*k, round(v[p], digits) + 0.0) for k, v in _cost_rows(mode, _GRID if fixed else _measured_grid(spark, sf))], "n double, b double, slots double, m double, t double, cost double")
        ORACLES[f"cost_{_part}_{_mode}"] = f"SELECT n, b, slots, m, t, round({_sql}, {_digits}) + 0.0 AS cost FROM {_part_sql(_mode, _GRID_SQL if _fixed_grid else _MEASURED_SQL)}"

_PLANS = [p.key for p in space.enumerate_plans()]


@query("plan_space_eleven", "WITH a(algorithm, s) AS (VALUES ('bgd', false), ('mgd', true), ('sgd', true)), t(transform) AS (VALUES ('eager'), ('lazy')), p(sampler) AS (VALUES ('none'), ('bernoulli'), ('random'), ('shuffle')) SELECT CASE WHEN s THEN algorithm||'-'||transform||'-'||sampler ELSE algorithm END AS plan, algorithm, transform, sampler FROM a, t, p WHERE (NOT s AND transform='eager' AND sampler='none') OR (s AND sampler<>'none' AND NOT (transform='lazy' AND sampler='bernoulli'))")
def _(spark, sf):
    return space.plan_space(spark)


def _plan_sql(grid: str = _GRID_SQL, d: int = 100) -> str:
    """Costs of the eleven plans over the grid, corrected mode, ``d`` features."""
    e = cost.Env()

    def io(n, b):
        full, k, tail, page = parts(n, b)
        return f"({full}*({e.seek} + {_S / e.page_bytes}*{page}) + CASE WHEN {tail} > 0 THEN {e.seek} + least({tail}, 1)*{k}*({b}/{n})/{e.page_bytes}*{page} ELSE 0 END)"

    def parts(n, b):
        share = f"least(1.0, {e.cache_bytes}/({b}))"
        full = f"floor(ceil(({b})/{_S})/slots)"
        return full, f"ceil(({n})*{_S}/({b}))", f"greatest(0.0, ({b})/{_S} - slots*{full})", f"({share}*{e.page_memory} + (1-{share})*{e.page})"

    def cpu(n, b, op):
        full, k, tail, _ = parts(n, b)
        return f"(({full}*{k} + ceil(least({tail}, 1)*{k}))*{e.cpu[op]})"

    def operator(op, n, b, on_driver):
        reads, _, sends = cost.MASK[op]
        here = f"(({n})*{e.cpu[op]} + {reads}*(({b})/{e.page_bytes})*{e.page_memory})"
        there = f"({reads}*{io(n, b)} + {cpu(n, b, op)} + {sends}*(({b})/{e.packet_bytes}*{e.net}*{e.packet_bytes}))"
        return f"(CASE WHEN {on_driver} THEN {here} ELSE {there} END)"

    one = ("1.0", f"{8.0 * d}")
    fits, batch = f"b <= {_S}", ("least(q, n)", "(least(q, n)*b/n)")
    small = f"q*b/greatest(n, 1) <= {_S}"
    closing = f"({operator('converge', *one, 'true')} + {operator('loop', *one, 'true')})"
    page = parts("n", "b")[3]
    k = f"least({parts('n', 'b')[1]}, n)"
    sample = f"""CASE sampler WHEN 'bernoulli' THEN {io("n", "b")} + {cpu("n", "b", "sample")}
      WHEN 'random' THEN q*({e.seek} + {page}) + q*{e.cpu["sample"]}
      ELSE ({e.seek} + least({_S}, b)/{e.page_bytes}*{page} + {k}*{e.cpu["shuffle"]})/greatest(1, floor({k}/q)) + q/{k}*least({_S}, b)/{e.page_bytes}*{e.page_memory} + q*{e.cpu["sample"]} END"""
    each = f"""CASE WHEN algorithm = 'bgd' THEN {operator("compute", "n", "b", fits)} + {operator("update", "n", "b", fits)} + {closing}
      ELSE {sample} + {operator("compute", *batch, small)} + {operator("update", *batch, small)} + {closing} + CASE WHEN transform = 'lazy' THEN {operator("transform", *batch, "true")} ELSE 0 END END"""
    prep = f"{cpu(*one, 'stage')} + CASE WHEN transform = 'eager' THEN {operator('transform', 'n', 'b', fits)} ELSE 0 END"
    return f"""SELECT n, b, slots, m, t, plan, k, round(prep, 6) + 0.0 AS prep_cost, round(each, 6) + 0.0 AS iter_cost, round(prep + t*each, 6) + 0.0 AS total_cost
FROM (SELECT *, {prep} AS prep, {each} AS each FROM (
  SELECT *, CASE WHEN algorithm = 'sgd' THEN 1.0::DOUBLE ELSE m END AS q FROM {grid},
  (VALUES {", ".join(f"({i}, '{p.key}', '{p.algorithm}', '{p.transform}', '{p.sampler}')" for i, p in enumerate(space.enumerate_plans()))}) p(k, plan, algorithm, transform, sampler)))"""


def _plan_costs(spark, grid: list[tuple]) -> DataFrame:
    rows = []
    for n, b, c, m, t in grid:
        for p in space.enumerate_plans():
            r = cost.plan_cost(p, cost.Data(n, b, 100), m, t, cost.Env(slots=c))
            rows.append((n, b, c, m, t, r["plan"], *(round(r[x], 6) + 0.0 for x in ("prep_cost", "iter_cost", "total_cost"))))
    return spark.createDataFrame(rows, "n long, b long, slots int, m int, t int, plan string, prep_cost double, iter_cost double, total_cost double")


@query("plan_cost_all", f"SELECT n::BIGINT AS n, b::BIGINT AS b, slots::INT AS slots, m::INT AS m, t::INT AS t, plan, prep_cost, iter_cost, total_cost FROM ({_plan_sql()})")
def _(spark, sf):
    return _plan_costs(spark, _GRID)


@query("plan_choice_grid", f"SELECT n::BIGINT AS n, b::BIGINT AS b, slots::INT AS slots, m::INT AS m, t::INT AS t, arg_min(plan, (total_cost, k)) AS plan FROM ({_plan_sql()}) GROUP BY n, b, slots, m, t")
def _(spark, sf):
    """The argmin of the table of costs, by an aggregate."""
    order = F.create_map(*(F.lit(x) for k, p in enumerate(_PLANS) for x in (p, k)))
    return QUERIES["plan_cost_all"](spark, sf).groupBy("n", "b", "slots", "m", "t").agg(F.min_by("plan", F.struct("total_cost", order[F.col("plan")])).alias("plan"))


@query("always_one_algorithm", f"SELECT n::BIGINT AS n, b::BIGINT AS b, slots::INT AS slots, m::INT AS m, t::INT AS t, split_part(plan, '-', 1) AS always, arg_min(plan, (total_cost, k)) AS plan, min(total_cost) AS total_cost FROM ({_plan_sql(_MEASURED_SQL)}) GROUP BY n, b, slots, m, t, split_part(plan, '-', 1)")
def _(spark, sf):
    """What a belief in one algorithm runs: the cheapest plan of batch descent, of MGD and of SGD, beside the choice over all."""
    order = F.create_map(*(F.lit(x) for k, p in enumerate(_PLANS) for x in (p, k)))
    rows = _plan_costs(spark, _measured_grid(spark, sf)).withColumn("always", F.substring_index("plan", "-", 1))
    return rows.groupBy("n", "b", "slots", "m", "t", "always").agg(F.min_by("plan", F.struct("total_cost", order[F.col("plan")])).alias("plan"), F.min("total_cost").alias("total_cost"))


_VARIANTS = {"svrg": (lambda units, gradient, cfg: descent.svrg(units, gradient, cfg, 20), 0.05), "line_search": (descent.bgd_line_search, 2.0)}


def _with_variants(f):
    """Runs ``f`` with variance reduction and line search among the algorithms."""
    for name, (run, scans) in _VARIANTS.items():
        descent.register_algorithm(name, run, scans=scans)
    try:
        return f()
    finally:
        for name in _VARIANTS:
            descent.unregister_algorithm(name)


@query("plan_space_registered", "SELECT plan FROM (VALUES " + ", ".join(f"('{p}')" for p in [*_PLANS, "svrg", "line_search"]) + ") v(plan)")
def _(spark, sf):
    return spark.createDataFrame([(p,) for p in _with_variants(lambda: [p.key for p in space.enumerate_plans()])], "plan string")


@query("choice_with_variants")
def _(spark, sf):
    """Thirteen plans over W2, the registered algorithms speculated by their own runs; the chosen one is run."""

    def run():
        units = samplers.with_parts(W2.units(spark, sf), 8)
        req = optimizer.Request("logistic", 0.01, max_iter=200)
        report = optimizer.optimise(units, req)
        fit = optimizer.execute(report.chosen, W2.units(spark, sf), lambda df: df, req, data=report.data)
        return [(r["plan"], r["iters"], r["total_cost"], r["plan"] == report.chosen.key, fit.iterations if r["plan"] == report.chosen.key else None, fit.status if r["plan"] == report.chosen.key else None) for r in report.rows]

    return spark.createDataFrame(_with_variants(run), "plan string, iters_est long, total_cost double, chosen boolean, iterations int, status string")


_ASKS = {"none": optimizer.Request(), "time": optimizer.Request(time_s=1e-9), "hour": optimizer.Request(time_s=3600.0), "epsilon": optimizer.Request(max_iter=10, epsilon_given=True)}
_NEEDED = 500
_ASKED_SQL = f"(SELECT count(*)::DOUBLE AS n, count(*)*{8.0 * W6.dim + 16}::DOUBLE AS b, {cost.Env().slots}::DOUBLE AS slots, {optimizer.Request().batch}::DOUBLE AS m, {_NEEDED}::DOUBLE AS t FROM events) g"
_ASKS_SQL = "(VALUES " + ", ".join(f"('{k}', {r.time_s or 'NULL'}::DOUBLE, {r.max_iter or 'NULL'}::BIGINT)" for k, r in _ASKS.items()) + ") v(asked, time_s, max_iter)"


@query("constraint_violations", f"SELECT asked, CASE WHEN cheapest > time_s THEN 'TIME' WHEN {_NEEDED} > max_iter THEN 'EPSILON,MAX_ITER' ELSE '' END AS violated FROM (SELECT min(total_cost) AS cheapest FROM ({_plan_sql(_ASKED_SQL, W6.dim)})), {_ASKS_SQL}")
def _(spark, sf):
    """Which constraints the chosen plan over the events can't meet."""
    data, its = optimizer.collect_stats(W6.units(spark, sf)), dict.fromkeys(("bgd", "mgd", "sgd"), _NEEDED)
    rows = []
    for k, req in _ASKS.items():
        chosen, found = optimizer.choose(req, data, cost.Env(), its)
        rows.append((k, ",".join(next(r["violated"] for r in found if r["plan"] == chosen.key))))
    return spark.createDataFrame(rows, "asked string, violated string")


@query("placement_by_partition", "SELECT * FROM (VALUES ('small', 'sample', 'driver'), ('small', 'compute', 'driver'), ('large', 'sample', 'cluster'), ('large', 'compute', 'driver')) v(data, op, place)")
def _(spark, sf):
    rows = []
    for name, data in (("small", cost.Data(1e4, 1e6, 10)), ("large", cost.Data(1e9, 1e12, 100))):
        place = cost.place_operators(data, 1000, cost.Env(), True)
        rows += [(name, op, place[op]) for op in ("sample", "compute")]
    return spark.createDataFrame(rows, "data string, op string, place string")


query("rule_based_choice", "SELECT p::INT AS partitions, a AS algorithm, t::BIGINT AS t, CASE WHEN a = 'bgd' THEN 'bgd' WHEN p <= 1 THEN a||'-eager-bernoulli' WHEN a = 'sgd' AND t < 100000 THEN 'sgd-lazy-shuffle' ELSE a||'-eager-shuffle' END AS plan FROM (VALUES (1), (80)) x(p), (VALUES ('bgd'), ('mgd'), ('sgd')) y(a), (VALUES (10), (1000000)) z(t)")(lambda spark, sf: spark.createDataFrame([(p, a, t, optimizer.rule_based_choice(p, a, t, 10**6).key) for p in (1, 80) for a in ("bgd", "mgd", "sgd") for t in (10, 10**6)], "partitions int, algorithm string, t long, plan string"))


@query("explain_plans")
def _(spark, sf):
    return language.run_sql(spark, sf, "q = EXPLAIN RUN svm ON event_heavy HAVING EPSILON 0.01")["q"]


# --- prediction, metrics, baselines, language ------------------------------------------------------------------------

_W2 = [-3.0, 5.5, -0.4, 0.3]
_PRED_SQL = f"SELECT unit_id, label, CASE WHEN {_z(_W2)} >= 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS prediction, {_z(_W2)} AS z FROM ({W2.sql()})"


def _pred(spark, sf):
    return optimizer.predictions(W2.units(spark, sf), np.array(_W2), "logistic")


query("predict_labels", f"SELECT unit_id, label, prediction FROM ({_PRED_SQL})")(lambda spark, sf: _pred(spark, sf).select("unit_id", "label", "prediction"))
query("testing_error", f"SELECT round(avg((prediction-label)*(prediction-label)), 6) AS mse_pm1, round(avg((prediction<>label)::INT), 6) AS mse_01, round(avg((prediction<>label)::INT), 6) AS error_rate, round(sqrt(avg((prediction-label)*(prediction-label))), 6) AS rmse FROM ({_PRED_SQL})")(
    lambda spark, sf: metrics.testing_error(_pred(spark, sf)).select(*(F.round(c, 6).alias(c) for c in ("mse_pm1", "mse_01", "error_rate", "rmse")))
)
_CM = "count(*) FILTER (prediction=1 AND label=1) AS tp, count(*) FILTER (prediction=1 AND label=-1) AS fp, count(*) FILTER (prediction=-1 AND label=1) AS fn, count(*) FILTER (prediction=-1 AND label=-1) AS tn"
query("classification_report", f"SELECT *, round(tp/(tp+fp), 6) AS precision, round(tp/(tp+fn), 6) AS recall, round(2.0*tp/(2*tp+fp+fn), 6) AS f1 FROM (SELECT {_CM} FROM ({_PRED_SQL}))")(
    lambda spark, sf: metrics.classification_report(_pred(spark, sf)).select("tp", "fp", "fn", "tn", *(F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")))
)
query("auc", f"SELECT round(sum(p*(below+n/2))/(sum(p)*sum(n)), 6) AS auc FROM (SELECT p, n, coalesce(sum(n) OVER (ORDER BY z ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE AS below FROM (SELECT z, count(*) FILTER (label>0)::DOUBLE AS p, count(*) FILTER (label<0)::DOUBLE AS n FROM ({_PRED_SQL}) GROUP BY z))")(
    lambda spark, sf: metrics.auc(_pred(spark, sf)).select(F.round("auc", 6).alias("auc"))
)
query("train_test_split_80_20", f"SELECT ({_rank(0, 'o_orderkey')} < {int(0.2 * samplers.SPAN)}) AS test, count(*) AS n FROM orders GROUP BY 1")(
    lambda spark, sf: (lambda s: s[0].select(F.lit(False).alias("test")).union(s[1].select(F.lit(True).alias("test"))))(metrics.split_80_20(tasks.table(spark, sf, "orders").select(F.col("o_orderkey").alias("unit_id")))).groupBy("test").agg(F.count("*").alias("n"))
)


@query("ols_normal_equations", "SELECT 0 AS j, round(regr_intercept(p_retailprice/1000, (p_partkey % 1000)/1000.0), 6) AS w FROM part UNION ALL SELECT 1, round(regr_slope(p_retailprice/1000, (p_partkey % 1000)/1000.0), 6) FROM part")
def _(spark, sf):
    return spark.createDataFrame([(j, round(float(x), 6)) for j, x in enumerate(baselines.ols_exact(W7.units(spark, sf)))], "j int, w double")


_B = descent_sql(W2.sql(), 4, "logistic", 5, cols="n_used").replace(", n_used FROM t WHERE i > 0", " FROM t WHERE i = 5")


def _last(spark, w) -> DataFrame:
    return spark.createDataFrame([(5, *(round(float(x), 6) + 0.0 for x in w))], "iter int, " + ", ".join(f"w{j} double" for j in range(len(w))))


query("baseline_library_bgd", _B)(lambda spark, sf: _last(spark, baselines.library_sgd(W2.units(spark, sf), "logistic", _fixed(5)).weights))
query("baseline_bernoulli_tree", _B)(lambda spark, sf: _last(spark, baselines.bernoulli_tree(W2.units(spark, sf), "logistic", _fixed(5)).weights))
query("baseline_matrix_blocks_bgd", _B)(lambda spark, sf: _last(spark, baselines.matrix_blocks_standin(W2.units(spark, sf), "logistic", _fixed(5))[0].weights))
query("baseline_fused_bgd", _B)(lambda spark, sf: _last(spark, baselines.fused_standin(W2.units(spark, sf), "logistic", _fixed(5)).weights))
query("baseline_handcoded_bgd", _B)(lambda spark, sf: _last(spark, baselines.handcoded_bgd(W2.units(spark, sf), "logistic", 5)))
# a sample of a tenth (MGD), and one of a few units that is empty once in a million draws (SGD)
_TENTH, _FEW = "0.1::DOUBLE", "(1 - pow(1e-6, 1.0::DOUBLE/(SELECT count(*) FROM u)))"


def _sampled_sql(fraction: str) -> str:
    return descent_sql(W6.sql(), 3, "hinge", 6, where=f"{_rank('t.i + 1', 'u.unit_id')} < {fraction} * 4294967296", cols="n_used", digits=5).replace(", n_used FROM t WHERE i > 0", " FROM t WHERE i = 6")


def _sampled(system: str, few: bool):
    def run(spark, sf):
        units = W6.units(spark, sf)
        share = samplers.boosted_fraction(units.count(), 1e-6) if few else 0.1
        if system == "fused":
            w = baselines.fused_standin(units, "hinge", _fixed(6), fraction=share).weights
        elif system == "matrix_blocks":
            w = baselines.matrix_blocks_standin(units, "hinge", _fixed(6), fraction=share)[0].weights
        else:
            w = baselines.handcoded_bgd(units, "hinge", 6, fraction=share)
        return spark.createDataFrame([(6, *(round(float(x), 5) + 0.0 for x in w))], "iter int, w0 double, w1 double, w2 double")

    return run


for _system in ("fused", "matrix_blocks", "handcoded"):
    for _kind, _fraction in (("mgd", _TENTH), ("sgd", _FEW)):
        QUERIES[f"baseline_{_system}_{_kind}"] = _sampled(_system, _kind == "sgd")
        ORACLES[f"baseline_{_system}_{_kind}"] = _sampled_sql(_fraction)


@query("baseline_handcoded_shuffled", ORACLES["sgd_shuffled_partition_hash"].replace("SELECT i AS iter", "SELECT * EXCLUDE (delta, n_used) FROM (SELECT i AS iter") + ") WHERE iter = 30")
def _(spark, sf):
    w = baselines.handcoded_shuffled(_laid(spark, sf), "hinge", 30, 1, 0.7)
    return spark.createDataFrame([(30, *(round(float(x), 6) + 0.0 for x in w))], "iter int, w0 double, w1 double, w2 double")


for _how in ("sql", "partials", "tree", "keyed"):
    QUERIES[f"aggregation_{_how}"] = lambda spark, sf, how=_how: _last(spark, descent.bgd(W2.units(spark, sf), "logistic", _fixed(5, aggregation=how)).weights)
    ORACLES[f"aggregation_{_how}"] = _B


@query("all_plans_run")
def _(spark, sf):
    raw = tasks.table(spark, sf, "events").withColumn("unit_id", F.col("event_id"))
    req = optimizer.Request("hinge", batch=200)
    rows = optimizer.run_all_plans(raw, lambda df: tasks.transform_columns(df, "unit_id", W6.label, W6.features), req, 4, _fixed(3))
    return spark.createDataFrame([(r["plan"], r["seconds"], r["layout_s"], r["iterations"], r["status"], r["units"], r["partitions"], r["bytes"]) for r in rows], "plan string, seconds double, layout_s double, iterations int, status string, units long, partitions long, bytes long")


@query("language_run_q")
def _(spark, sf):
    s = language.Session(spark, sf)
    s.execute("q = RUN svm ON event_heavy HAVING EPSILON 0.05, MAX_ITER 30 USING ALGORITHM bgd, STEP 1")
    return model_frame(spark, s.models["q"])


_M_SQL = descent_sql(W7.sql(), 2, "linear", 12, beta=0.45).replace(_rounded(["w0", "w1"]), "w0, w1")


@query("language_persist_predict", f"SELECT unit_id, label, round(f.w0 + f.w1*x1, 4) AS prediction FROM ({W7.sql()}) p, (SELECT * FROM ({_M_SQL}) WHERE iter = 12) f")
def _(spark, sf):
    path = _folder(spark, "model")
    out = language.run_sql(spark, sf, f"m = RUN linear ON part_price HAVING EPSILON 0.000000001, MAX_ITER 12 USING ALGORITHM bgd, STEP 0.45; PERSIST m ON '{path}'; r = PREDICT ON part_price WITH '{path}'")["r"]
    return out.select("unit_id", "label", F.round("prediction", 4).alias("prediction"))


query("order_total_units", "SELECT o_orderkey AS unit_id, o_totalprice/5e5 AS label, round(c_acctbal/10000, 6) AS x1 FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")(
    lambda spark, sf: tasks.order_total(spark, sf).select("unit_id", "label", F.round(F.col("features")[1], 6).alias("x1"))
)
query("embedding_label_units", "SELECT vec_id AS unit_id, CASE WHEN label = 1 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label FROM embeddings")(lambda spark, sf: tasks.embedding_label(spark, sf, 1).select("unit_id", "label"))


@query("fit_per_group", None)
def _(spark, sf):
    """One model a group: the event types of events, each fitted in its own task."""
    import pandas as pd

    def one(f: pd.DataFrame) -> pd.DataFrame:
        x = np.column_stack([np.ones(len(f)), f["value"] / 100])
        y = np.where(f["value"] > 50, 1.0, -1.0)
        w = np.zeros(2)
        for i in range(1, 51):
            w = w - descent.compute_local(x, y, w, GRADIENTS["logistic"]).grad / len(f) / math.sqrt(i)
        return pd.DataFrame({"event_type": [f["event_type"].iloc[0]], "w0": [w[0]], "w1": [w[1]]})

    return tasks.table(spark, sf, "events").select("event_type", "value").groupBy("event_type").applyInPandas(one, "event_type string, w0 double, w1 double")

