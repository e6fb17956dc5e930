"""Queries on the theory: risks, lengths, probabilities, variances, draws and short training runs.

Each has a DuckDB twin over the same tables.  Parameters are fixed, so both engines score alike.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import columns as C
from ..functions import features as X
from ..functions.objectives import Linear, Mlp, Pca, outer_lengths
from ..functions.steps import constant
from ..operators import draws as D
from ..operators import history as H
from ..operators import measures as M
from ..sources.tables import checkpointed, read_table
from . import trainers as T

FEATURES = ["x1", "x2", "x3", "x4", "x0"]
W = [4.0, -0.5, 0.3, 0.1, 0.2]
SEED, BETA, SHARDS = 7, 0.2, 16

INST = """
stats AS (SELECT avg(l_extendedprice) a1, stddev_pop(l_extendedprice) s1, avg(l_discount) a2, stddev_pop(l_discount) s2,
  avg(l_quantity) a3, stddev_pop(l_quantity) s3, avg(l_tax) a4, stddev_pop(l_tax) s4 FROM lineitem),
inst AS (SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT)) AS instance_id,
  (l_extendedprice - a1) / s1 AS x1, (l_discount - a2) / s2 AS x2, (l_quantity - a3) / s3 AS x3, (l_tax - a4) / s4 AS x4, 1.0::DOUBLE AS x0,
  l_extendedprice * (1 - l_discount) AS net,
  CASE WHEN l_extendedprice * (1 - l_discount) > 50000 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label FROM lineitem, stats)"""
SCORE = " + ".join(f"({w}::DOUBLE) * {c}" for w, c in zip(W, FEATURES, strict=True))
LOSS = {"squared": "(s - label) * (s - label)", "hinge": "greatest(0.0, 1.0 - s * label)", "logistic": "ln(1.0 + exp(-abs(s * label))) + greatest(-(s * label), 0.0)"}
SLOPE = {"squared": "2.0 * (s - label)", "hinge": "CASE WHEN s * label < 1 THEN -label ELSE 0.0 END", "logistic": "-label / (1.0 + exp(s * label))"}


def scored_sql(kind: str) -> str:
    return f"""{INST}, sc0 AS (SELECT *, {SCORE} AS s, {" + ".join(f"{c} * {c}" for c in FEATURES)} AS sq FROM inst),
sc AS (SELECT *, {LOSS[kind]} AS loss, {SLOPE[kind]} AS slope, abs({SLOPE[kind]}) * sqrt(sq) AS len FROM sc0)"""


def uniform_sql(*parts: str) -> str:
    text = " || ':' || ".join(p if p.startswith(("CAST", "inst", "'")) else f"'{p}'" for p in parts)
    return f"((('0x' || substr(md5({text}), 1, 12))::BIGINT + 0.5) / {C.SPAN!r})"


def scored(spark: SparkSession, sf_dir: str, kind: str = "logistic") -> DataFrame:
    return M.scored(X.net_price(spark, sf_dir), FEATURES, W, kind)


def r6(name: str, out: str | None = None):
    return (F.round(F.col(name), 6) + 0.0).alias(out or name)


def _with_shard(df: DataFrame) -> DataFrame:
    return df.withColumn("shard", X.shard_of(F.col("instance_id"), SHARDS))


SHARD_SQL = f"CAST(floor({uniform_sql('shard', 'instance_id')} * {SHARDS}) AS INTEGER)"


def _risk(kind: str):
    return lambda s, d: M.empirical_risk(scored(s, d, kind)).select(r6("risk")), f"WITH {scored_sql(kind)} SELECT round(avg(loss), 6) AS risk FROM sc"


def zero_one(s: SparkSession, d: str) -> DataFrame:
    return scored(s, d).agg(F.avg(C.loss("zero_one", F.col("score"), F.col("label"))).alias("error")).select(r6("error"))


def _objective(kind: str):
    lam = 0.01
    pen = lam * (sum(w * w for w in W) if kind == "l2" else sum(abs(w) for w in W))
    return lambda s, d: M.empirical_risk(scored(s, d)).select(F.round(F.col("risk") + pen, 6).alias("objective")), f"WITH {scored_sql('logistic')} SELECT round(avg(loss) + {pen!r}, 6) AS objective FROM sc"


def gradient_step(s: SparkSession, d: str) -> DataFrame:
    return M.full_gradient(scored(s, d), FEATURES).select(*[r6(f"g_{c}") for c in FEATURES])


def descent_10(s: SparkSession, d: str) -> DataFrame:
    """Ten full-gradient steps; each is one aggregation, five numbers reach the driver."""
    data, w = X.net_price(s, d), np.zeros(5)
    out = []
    for t in range(1, 11):
        row = M.full_gradient(M.scored(data, FEATURES, w.tolist(), "logistic"), FEATURES).first()
        w = w - 0.5 * np.array(list(row))
        out.append((t, *[round(float(v), 6) + 0.0 for v in w]))
    return s.createDataFrame(out, "step int, " + ", ".join(f"w_{c} double" for c in FEATURES))


def descent_sql(steps: int = 10, eta: float = 0.5) -> str:
    ctes = [INST, f"w0 AS MATERIALIZED (SELECT {', '.join(f'0.0::DOUBLE AS w_{c}' for c in FEATURES)})"]
    for t in range(1, steps + 1):
        s = " + ".join(f"w_{c} * {c}" for c in FEATURES)
        ctes.append(f"w{t} AS MATERIALIZED (SELECT {', '.join(f'any_value(w_{c}) - {eta} * avg(-label / (1.0 + exp(({s}) * label)) * {c}) AS w_{c}' for c in FEATURES)} FROM inst, w{t - 1})")
    return f"WITH {', '.join(ctes)} " + " UNION ALL ".join(f"SELECT {t} AS step, {', '.join(f'round(w_{c}, 6) + 0.0 AS w_{c}' for c in FEATURES)} FROM w{t}" for t in range(1, steps + 1))


def lengths_top20(s: SparkSession, d: str) -> DataFrame:
    return scored(s, d).select("instance_id", r6("len")).orderBy(F.desc("len"), "instance_id").limit(20)


def _gain(kind: str, top: int):
    def q(s: SparkSession, d: str) -> DataFrame:
        return M.gain_columns(scored(s, d), 1, kind).select("instance_id", r6("uncertainty"), r6("significance"), r6("gain")).orderBy(F.desc("gain"), "instance_id").limit(top)

    p = "(1.0 / (1.0 + exp(-s)))"
    u = f"(-{p} * ln({p}) - (1 - {p}) * ln(1 - {p}))" if kind == "entropy" else f"(2.0 * {p} * (1 - {p}))"
    return q, f"WITH {scored_sql('logistic')} SELECT instance_id, round({u}, 6) AS uncertainty, round(sqrt(sq), 6) AS significance, round({u} * sqrt(sq), 6) AS gain FROM sc ORDER BY gain DESC, instance_id LIMIT {top}"


def exact_probabilities(s: SparkSession, d: str) -> DataFrame:
    own = scored(s, d)
    total = own.agg(F.sum("len").alias("total"))
    p = (F.col("len") / F.col("total")).alias("p")
    return own.join(F.broadcast(total)).select(p).agg(F.round(F.sum("p"), 6).alias("sum_p"), F.round(F.max("p") * 1e6, 4).alias("max_p_millionths"), F.round(F.stddev_pop("p") * 1e6, 4).alias("std_p_millionths"), F.count(F.when(F.col("p") > 0, 1)).alias("positive"))


def _stored(s: SparkSession, d: str) -> DataFrame:
    """A stand-in history: lengths from hashes."""
    own = X.net_price(s, d).select("instance_id")
    return _with_shard(own).withColumns({"magnitude": C.hash_uniform("hist", F.col("instance_id")), "last_step": F.lit(0).cast("long")})


STORED_SQL = f"{INST}, stored AS (SELECT instance_id, {SHARD_SQL} AS shard, {uniform_sql('hist', 'instance_id')} AS magnitude FROM inst)"


def history_probabilities(s: SparkSession, d: str) -> DataFrame:
    p = H.probabilities(_stored(s, d), BETA)
    return p.select("instance_id", F.round(F.col("prob") * 1e6, 3).alias("prob_millionths")).orderBy(F.desc("prob_millionths"), "instance_id").limit(50)


def floor_check(s: SparkSession, d: str) -> DataFrame:
    p = H.probabilities(_stored(s, d), BETA)
    return p.agg(F.round(F.min("prob") * F.count(F.lit(1)), 6).alias("least_np"), F.round(F.sum("prob"), 6).alias("sum_p"), (F.min("prob") * F.count(F.lit(1)) >= BETA).alias("floor_holds"))


VAR_SQL = "count(*) AS n, sum(len) AS s1, sum(len * len) AS s2, " + " + ".join(f"avg(slope * {c}) * avg(slope * {c})" for c in FEATURES) + " AS g"


def variance_report(s: SparkSession, d: str, batch: int = 1) -> DataFrame:
    return M.variance_report(scored(s, d), FEATURES, None, batch).select("n", r6("var_uniform"), r6("var_least"), r6("ratio_least"))


def _variance_sql(batch: int) -> str:
    return f"WITH {scored_sql('logistic')}, v AS (SELECT {VAR_SQL} FROM sc) SELECT n, round((s2 / n - g) / {batch}, 6) AS var_uniform, round((s1 / n * s1 / n - g) / {batch}, 6) AS var_least, round((s1 / n * s1 / n - g) / (s2 / n - g), 6) AS ratio_least FROM v"


def equivalent_batch(s: SparkSession, d: str) -> DataFrame:
    own = scored(s, d)
    total = own.agg(F.sum("len").alias("t"), F.count(F.lit(1)).alias("m"))
    p = 0.8 * F.col("len") / F.col("t") + 0.2 / F.col("m")
    return M.variance_report(own.join(F.broadcast(total)).withColumn("p", p), FEATURES, F.col("p")).select(r6("var_given"), r6("ratio_given"), r6("equal_batch"))


EQUIV_SQL = f"""WITH {scored_sql("logistic")}, t AS (SELECT sum(len) t, count(*) m FROM sc), q AS (SELECT *, 0.8 * len / t + 0.2 / m AS p FROM sc, t),
v AS (SELECT {VAR_SQL}, sum(len * len / p) AS inv FROM q), r AS (SELECT s2 / n - g AS u, inv / n / n - g AS h FROM v)
SELECT round(h, 6) AS var_given, round(h / u, 6) AS ratio_given, round(u / h, 6) AS equal_batch FROM r"""


def unbiasedness(s: SparkSession, d: str, reweight: bool = True) -> DataFrame:
    own = scored(s, d)
    total = own.agg(F.sum("len").alias("t"), F.count(F.lit(1)).alias("m"))
    q = own.join(F.broadcast(total)).withColumn("p", 0.8 * F.col("len") / F.col("t") + 0.2 / F.col("m"))
    return M.bias_norm(q, FEATURES, F.col("p"), reweight).select(r6("bias_norm"))


BIASED_SQL = f"""WITH {scored_sql("logistic")}, t AS (SELECT sum(len) t, count(*) m FROM sc), q AS (SELECT *, 0.8 * len / t + 0.2 / m AS p FROM sc, t)
SELECT round(sqrt({" + ".join(f"pow(sum(p * slope * {c}) - avg(slope * {c}), 2)" for c in FEATURES)}), 6) AS bias_norm FROM q"""


def equal_lengths(s: SparkSession, d: str) -> DataFrame:
    own = scored(s, d)
    total = own.agg(F.sum("len").alias("t"))
    return M.weighted_length_spread(own.join(F.broadcast(total)), F.col("len") / F.col("t")).select(r6("least"), r6("greatest"), r6("mean_length"))


def _draw_out(df: DataFrame) -> DataFrame:
    return df.select(F.col("draw_no").cast("int").alias("draw_no"), "instance_id", F.round(F.col("prob") * 1e6, 3).alias("prob_millionths"), F.round("weight", 4).alias("weight"))


def uniform_draw(s: SparkSession, d: str) -> DataFrame:
    return _draw_out(D.uniform_draw(_stored_once(s, d), 128, SEED, 1))


def weighted_draw(s: SparkSession, d: str) -> DataFrame:
    return _draw_out(D.two_level_draw(_stored_once(s, d), "magnitude", 128, SEED, 1))


def mixture(s: SparkSession, d: str) -> DataFrame:
    return _draw_out(D.mixture_draw(_stored_once(s, d), "magnitude", BETA, 128, SEED, 2))


def _draw_sql(step: int, mix: bool = False, flat: bool = False) -> str:
    weight = "1.0::DOUBLE" if flat else "magnitude"
    us = f"us AS (SELECT j AS draw_no, {uniform_sql(str(SEED), str(step), 'CAST(j AS VARCHAR)')} AS u FROM range(128) r(j))"
    cum = f"cum AS (SELECT instance_id, {weight} AS m, sum({weight}) OVER (ORDER BY shard, instance_id) AS hi, sum({weight}) OVER () AS total, count(*) OVER () AS n, row_number() OVER (ORDER BY shard, instance_id) AS k FROM stored)"
    if mix:
        hit = f"(u < {BETA} AND u / {BETA} * n >= k - 1 AND u / {BETA} * n < k) OR (u >= {BETA} AND (u - {BETA}) / {1 - BETA} * total >= hi - m AND (u - {BETA}) / {1 - BETA} * total < hi)"
        p = f"({1 - BETA} * m / total + {BETA} / n)"
    else:
        hit, p = "u * total >= hi - m AND u * total < hi", "(m / total)"
    return f"WITH {STORED_SQL}, {us}, {cum} SELECT draw_no::INTEGER AS draw_no, instance_id, round({p} * 1e6, 3) AS prob_millionths, round(1.0 / (n * {p}), 4) AS weight FROM us JOIN cum ON {hit}"


VISIT_STEPS = range(1, 41)


def _visits(s: SparkSession, d: str) -> DataFrame:
    return M.visit_table(D.block_draw(_stored_once(s, d), "magnitude", 32, SEED, VISIT_STEPS))


def visit_counts(s: SparkSession, d: str) -> DataFrame:
    """Most visited rows of forty frozen batches."""
    return _visits(s, d).orderBy(F.desc("visits"), "instance_id").limit(20)


def staleness_report(s: SparkSession, d: str) -> DataFrame:
    """Steps since the last visit over all rows; rows never visited count from the start."""
    stored = _stored_once(s, d)
    seen = F.broadcast(M.visit_table(D.block_draw(stored, "magnitude", 32, SEED, VISIT_STEPS)))  # a row a draw at most
    age = F.lit(VISIT_STEPS.stop - 1) - F.coalesce("last_step", F.lit(0))
    every = stored.select("instance_id").join(seen, "instance_id", "left").withColumn("age", age)
    return every.agg(
        F.count("visits").alias("visited"), F.round(F.avg("age"), 6).alias("mean_age"), F.round(F.avg(F.when(F.col("visits").isNotNull(), F.col("age"))), 6).alias("mean_age_visited"),
        F.percentile(F.when(F.col("visits").isNotNull(), F.col("age")), F.lit(0.5)).alias("median_age_visited"), F.percentile(F.when(F.col("visits").isNotNull(), F.col("age")), F.lit(0.9)).alias("p90_age_visited"), F.max("age").cast("long").alias("max_age"), F.sum("visits").alias("draws"),
    )


VISITS_SQL = f"""{STORED_SQL}, us AS (SELECT t, {uniform_sql(str(SEED), "CAST(t AS VARCHAR)", "CAST(j AS VARCHAR)")} AS u FROM range(1, 41) a(t), range(32) b(j)),
cum AS (SELECT instance_id, magnitude AS m, sum(magnitude) OVER (ORDER BY shard, instance_id) AS hi, sum(magnitude) OVER () AS total FROM stored),
ends AS (SELECT t, u * (SELECT any_value(total) FROM cum) AS target FROM us),
hit AS (SELECT t, instance_id FROM ends ASOF JOIN (SELECT instance_id, hi - m AS lo FROM cum) c ON ends.target >= c.lo),
vis AS (SELECT instance_id, count(*) AS visits, max(t) AS last_step FROM hit GROUP BY 1)"""


def poisson(s: SparkSession, d: str) -> DataFrame:
    stored = _stored_once(s, d)
    h, n = H.probabilities(stored, BETA), stored.count()
    return D.poisson_draw(h, "prob", 256, n, SEED, 3).select("instance_id", F.col("copies").cast("int").alias("copies"), F.round("weight", 4).alias("weight"))


def _poisson_sql() -> str:
    term, terms = "exp(-rate)", ["exp(-rate)"]
    for k in range(1, 13):
        term = f"{term} * rate / {k}"
        terms.append(term)
    copies = " + ".join(f"(CASE WHEN u >= {' + '.join(terms[: k + 1])} THEN 1 ELSE 0 END)" for k in range(12))
    return f"""WITH {STORED_SQL}, pr AS (SELECT instance_id, {1 - BETA} * magnitude / sum(magnitude) OVER () + {BETA} / count(*) OVER () AS p, count(*) OVER () AS n FROM stored),
q AS (SELECT *, 256.0 * p AS rate, {uniform_sql(str(SEED), "3", "instance_id")} AS u FROM pr), c AS (SELECT *, {copies} AS copies FROM q)
SELECT instance_id, copies::INTEGER AS copies, round(1.0 / (n * p), 4) AS weight FROM c WHERE copies > 0"""


def subset(s: SparkSession, d: str) -> DataFrame:
    return D.subset_without_replacement(X.net_price(s, d).select("instance_id"), 200, SEED, 1).select("instance_id", F.round("u", 9).alias("u"))


def subset_large(s: SparkSession, d: str) -> DataFrame:
    """The same subset through a hash threshold, as for large m."""
    own = X.net_price(s, d).select("instance_id")
    return D.subset_by_threshold(own, 200, own.count(), SEED, 1).select("instance_id", F.round("u", 9).alias("u"))


def preview(s: SparkSession, d: str) -> DataFrame:
    """Weighted sample without replacement, by exponential keys."""
    return D.exponential_key_topk(_stored(s, d), "magnitude", 100, SEED).select("instance_id", F.round(F.col("key") * 1e6, 3).alias("key_millionths"))


def holdout_risk(s: SparkSession, d: str) -> DataFrame:
    own = scored(s, d).where(X.hash_split(F.col("instance_id"), 20))
    return own.agg(F.count(F.lit(1)).alias("rows"), F.round(F.avg("loss"), 6).alias("risk"), F.round(F.avg(C.loss("zero_one", F.col("score"), F.col("label"))), 6).alias("error"))


def class_probability(s: SparkSession, d: str) -> DataFrame:
    p = C.probability(F.col("score"), F.col("label"))
    return scored(s, d).groupBy(F.col("label").cast("int").alias("label")).agg(F.round(F.avg(p), 6).alias("p"), F.round(F.avg(C.entropy(p)), 6).alias("entropy"), F.count(F.when(p > 0.5, 1)).alias("right"))


def stage_and_length_costs(s: SparkSession, d: str) -> DataFrame:
    """Benefit share of a stage and the relative cost of lengths, from the given tables' sizes."""
    n = X.net_price(s, d).count() // 16
    steps = 16 * n // 128
    return s.createDataFrame([(n, round(M.benefit_share(n, max(1, steps), 128), 6), round(M.length_cost(128, 32, 64), 6))], "rows long, benefit double, length_cost double")


def _stored_once(s: SparkSession, d: str) -> DataFrame:
    """The stored lengths as a table, for draws, which read them more than once."""
    return checkpointed(_stored(s, d), "stored")


def shard_masses(s: SparkSession, d: str) -> DataFrame:
    return D.shard_masses(_stored(s, d), "magnitude").select("shard", "rows", r6("mass"))


def two_level_vs_global(s: SparkSession, d: str) -> DataFrame:
    """The two-level draw and the running sum over the whole table must name the same rows."""
    stored = _stored_once(s, d)
    a = D.two_level_draw(stored, "magnitude", 64, SEED, 5).select("draw_no", F.col("instance_id").alias("a"))
    b = D.global_cdf_draw(stored, "magnitude", 64, SEED, 5).select("draw_no", F.col("instance_id").alias("b"))
    return a.join(b, "draw_no", "full").agg(F.count(F.lit(1)).alias("draws"), F.count(F.when(F.col("a") == F.col("b"), 1)).alias("same"))


def proximal(s: SparkSession, d: str) -> DataFrame:
    """Stage objective at W, with the stage's start at zero and a pull of 0.3."""
    own = D.subset_without_replacement(scored(s, d), 1000, SEED, 2)
    pull = 0.15 * sum(w * w for w in W)
    return own.agg(F.count(F.lit(1)).alias("rows"), F.round(F.avg("loss") + pull, 6).alias("objective"))


PROXIMAL_SQL = f"WITH {scored_sql('logistic')}, sub AS (SELECT * FROM sc ORDER BY {uniform_sql(str(SEED), '2', 'instance_id')}, instance_id LIMIT 1000) SELECT count(*) AS rows, round(avg(loss) + {0.15 * sum(w * w for w in W)!r}, 6) AS objective FROM sub"


def _directions(classes: int) -> np.ndarray:
    return X.planted_directions(64, classes, 11)


def softmax_lengths(s: SparkSession, d: str) -> DataFrame:
    """Lengths of soft-max regression on the given label, at fixed parameters, from two row norms."""
    obj = Mlp((64, 10), include_bias=False)
    w = np.concatenate([_directions(10).ravel(), np.zeros(10)])
    data = read_table(s, d, "embeddings").select(F.col("vec_id").alias("instance_id"), F.lit(0).alias("shard"), F.col("embedding").cast("array<double>").alias("features"), F.col("label").cast("double").alias("label"))
    return T.row_lengths(data, obj, w).select("instance_id", r6("magnitude"))


def _list_sql(a: np.ndarray) -> str:
    return "[" + ", ".join(repr(float(v)) for v in a) + "]"


def _softmax_sql() -> str:
    rows = ", ".join(_list_sql(r) for r in _directions(10))
    return f"""WITH dirs AS (SELECT [{rows}] AS ds), z AS (SELECT vec_id, label, embedding::DOUBLE[] AS x, list_transform(ds, lambda q: list_dot_product(embedding::DOUBLE[], q)) AS z FROM embeddings, dirs),
p AS (SELECT vec_id, label, x, list_transform(z, lambda v: exp(v)) AS e FROM z),
q AS (SELECT vec_id, x, list_transform(e, lambda v, i: v / list_sum(e) - CASE WHEN i = label + 1 THEN 1 ELSE 0 END) AS g FROM p)
SELECT vec_id AS instance_id, round(sqrt(list_dot_product(g, g) * list_dot_product(x, x)), 6) AS magnitude FROM q"""


def softmax_bruteforce(s: SparkSession, d: str) -> DataFrame:
    """The same lengths from one explicit gradient for each row."""
    obj = Mlp((64, 10))
    w = np.concatenate([_directions(10).ravel(), np.zeros(10)])

    def run(batches):
        for pdf in batches:
            x, y = T._matrix(pdf)
            yield pdf[["instance_id"]].assign(magnitude=outer_lengths(obj, w, x, y, weights_only=True))

    data = read_table(s, d, "embeddings").select(F.col("vec_id").alias("instance_id"), F.col("embedding").cast("array<double>").alias("features"), F.col("label").cast("double").alias("label"))
    return data.mapInPandas(run, "instance_id long, magnitude double").select("instance_id", r6("magnitude"))


def pca_lengths(s: SparkSession, d: str) -> DataFrame:
    obj, w = Pca(64, 2), _directions(2).T.ravel()
    data = read_table(s, d, "embeddings").select(F.col("vec_id").alias("instance_id"), F.lit(0).alias("shard"), F.col("embedding").cast("array<double>").alias("features"), F.lit(None).cast("double").alias("label"))
    return T.row_lengths(data, obj, w).select("instance_id", r6("magnitude"))


def _pca_sql() -> str:
    """Length of the explicit gradient matrix 2 (r a' + x c'), entry by entry."""
    d0, d1 = (_list_sql(r) for r in _directions(2))
    return f"""WITH a AS (SELECT vec_id, embedding::DOUBLE[] AS x, {d0} AS u, {d1} AS v FROM embeddings),
b AS (SELECT *, list_dot_product(x, u) AS a0, list_dot_product(x, v) AS a1 FROM a),
c AS (SELECT *, list_transform(x, lambda e, i: u[i] * a0 + v[i] * a1 - e) AS r FROM b),
e AS (SELECT *, list_dot_product(r, u) AS c0, list_dot_product(r, v) AS c1 FROM c)
SELECT vec_id AS instance_id, round(sqrt(list_sum(list_transform(x, lambda e, i: 4 * (pow(r[i] * a0 + e * c0, 2) + pow(r[i] * a1 + e * c1, 2))))), 6) AS magnitude FROM e"""


def _instances(s: SparkSession, d: str) -> DataFrame:
    own = _with_shard(X.net_price(s, d))
    return checkpointed(own.select("instance_id", "shard", F.lit(False).alias("is_valid"), F.array(*FEATURES).alias("features"), "label"), "instances")


def _short(method: str):
    def q(s: SparkSession, d: str) -> DataFrame:
        """Five steps over the whole table, one distributed job a step."""
        r = T.train(method, _instances(s, d), Linear("logistic", 5), steps=5, batch=4, step_rule=constant(0.5), seed=SEED, eval_every=0, beta=BETA, exec_mode="per_step", init="constant")
        return s.createDataFrame([(5, *[round(float(v), 6) + 0.0 for v in r.model])], "step int, " + ", ".join(f"w_{c} double" for c in FEATURES))

    return q


def _loop_sql(rows: str, tag: str, start: str, steps: range, method: str, n: int | str, gamma: float = 0.0) -> list[str]:
    """CTEs of stochastic steps over the rows of CTE `rows` (i, x.., label); model w_<tag><t>."""
    out = [f"{tag}m{steps.start - 1} AS MATERIALIZED (SELECT i, 1.0::DOUBLE AS m FROM {rows})"]
    s = " + ".join(f"w.w_{c} * r.{c}" for c in FEATURES)
    for t in steps:
        prev = start if t == steps.start else f"{tag}w{t - 1}"
        p = f"(1.0 / {n})" if method == "uniform" else f"({1 - BETA} * m / sum(m) OVER () + {BETA} / {n})"
        out += [
            f"{tag}p{t} AS MATERIALIZED (SELECT i, {p} AS p FROM {tag}m{t - 1})",
            f"{tag}c{t} AS MATERIALIZED (SELECT i, p, sum(p) OVER (ORDER BY i) AS hi FROM {tag}p{t})",
            f"{tag}d{t} AS MATERIALIZED (SELECT j, i, p FROM (SELECT j, {uniform_sql(str(SEED), str(t), 'CAST(j AS VARCHAR)')} AS u FROM range(4) g(j)) JOIN {tag}c{t} ON u >= hi - p AND u < hi)",
            f"{tag}g{t} AS MATERIALIZED (SELECT i, p, x1, x2, x3, x4, x0, -label / (1.0 + exp(({s}) * label)) AS slope FROM {tag}d{t} JOIN {rows} r USING (i), {prev} w)",
            f"{tag}w{t} AS MATERIALIZED (SELECT {', '.join(f'any_value(w.w_{c}) - 0.5 * (sum(slope * {c} / ({n} * p)) / 4 + {gamma} * (any_value(w.w_{c}) - any_value(b.w_{c}))) AS w_{c}' for c in FEATURES)} FROM {tag}g{t}, {prev} w, {start} b)",
            f"{tag}m{t} AS MATERIALIZED (SELECT m.i, coalesce(any_value(abs(slope) * sqrt(x1*x1 + x2*x2 + x3*x3 + x4*x4 + x0*x0)), any_value(m.m)) AS m FROM {tag}m{t - 1} m LEFT JOIN {tag}g{t} g ON m.i = g.i GROUP BY m.i)",
        ]
    return out


def _subset_sql(name: str, source: str, m: int, stage: int) -> str:
    return f"{name} AS MATERIALIZED (SELECT row_number() OVER (ORDER BY instance_id) - 1 AS i, * FROM (SELECT instance_id, x1, x2, x3, x4, x0, label FROM {source} ORDER BY {uniform_sql(str(SEED), str(stage), 'instance_id')}, instance_id LIMIT {m}))"


ZERO_W = f"z0 AS MATERIALIZED (SELECT {', '.join(f'0.0::DOUBLE AS w_{c}' for c in FEATURES)})"
MODEL_OUT = ", ".join(f"round(w_{c}, 6) + 0.0 AS w_{c}" for c in FEATURES)


def _short_sql(method: str) -> str:
    every = f"every AS MATERIALIZED (SELECT row_number() OVER (ORDER BY shard, instance_id) - 1 AS i, * FROM (SELECT *, {SHARD_SQL} AS shard FROM inst))"
    return f"WITH {', '.join([INST, every, ZERO_W, *_loop_sql('every', 'a', 'z0', range(1, 6), method, '(SELECT count(*) FROM every)')])} SELECT 5 AS step, {MODEL_OUT} FROM aw5"


def staged_short(s: SparkSession, d: str) -> DataFrame:
    """Two stages of four steps, each on 1,000 fresh rows of the whole table."""
    r = T.staged_history(_instances(s, d), Linear("logistic", 5), 2, subset_rows=1000, batch=4, inner_steps=4, proximity="constant", gamma0=0.1, beta=BETA, history="reset", step_rule=constant(0.5), seed=SEED, eval_every=0)
    return s.createDataFrame([(8, *[round(float(v), 6) + 0.0 for v in r.model])], "step int, " + ", ".join(f"w_{c} double" for c in FEATURES))


def _staged_sql() -> str:
    ctes = [INST, ZERO_W, _subset_sql("st0", "inst", 1000, 0), *_loop_sql("st0", "a", "z0", range(1, 5), "history", 1000, 0.1), _subset_sql("st1", "inst", 1000, 1), *_loop_sql("st1", "b", "aw4", range(5, 9), "history", 1000, 0.1)]
    return f"WITH {', '.join(ctes)} SELECT 8 AS step, {MODEL_OUT} FROM bw8"


def _one_step(method: str):
    """One distributed step from W over all rows: draws by shard masses, rows fetched by broadcast."""

    def q(s: SparkSession, d: str) -> DataFrame:
        own = checkpointed(_with_shard(scored(s, d)).select("instance_id", "shard", *FEATURES, "slope", "len"), "scored")
        if method == "uniform":
            picked = D.uniform_draw(own.select("instance_id", "shard"), 128, SEED, 4)
        elif method == "exact":
            picked = D.two_level_draw(own.select("instance_id", "shard", "len"), "len", 128, SEED, 4)
        else:
            held = own.select("instance_id", "shard", C.hash_uniform("hist", F.col("instance_id")).alias("magnitude"))
            picked = D.two_level_draw(checkpointed(H.probabilities(held, BETA), "probabilities"), "prob", 128, SEED, 4)
        rows = own.join(F.broadcast(picked.select("instance_id", "weight")), "instance_id")
        return rows.agg(F.count(F.lit(1)).alias("draws"), *[F.round(F.lit(w) - 0.1 * F.sum(F.col("weight") * F.col("slope") * F.col(c)) / 128, 6).alias(f"w_{c}") for w, c in zip(W, FEATURES, strict=True)])

    m = {"uniform": "1.0::DOUBLE", "exact": "len", "history": f"({1 - BETA} * {uniform_sql('hist', 'instance_id')} / (SELECT sum(magnitude) FROM stored) + {BETA} / (SELECT count(*) FROM stored))"}[method]
    scored_part = scored_sql("logistic").replace(INST, "", 1)
    sql = f"""WITH {STORED_SQL}{scored_part}, b AS (SELECT *, {m} AS m, {SHARD_SQL} AS shard FROM sc),
cum AS (SELECT *, sum(m) OVER (ORDER BY shard, instance_id) AS hi, sum(m) OVER () AS total, count(*) OVER () AS n FROM b),
us AS (SELECT {uniform_sql(str(SEED), "4", "CAST(j AS VARCHAR)")} AS u FROM range(128) r(j)),
dr AS (SELECT * FROM us JOIN cum ON u * total >= hi - m AND u * total < hi)
SELECT count(*) AS draws, {", ".join(f"round({w} - 0.1 * sum(slope * {c} * total / (n * m)) / 128, 6) AS w_{c}" for w, c in zip(W, FEATURES, strict=True))} FROM dr"""
    return q, sql


def queries() -> dict[str, tuple]:
    """Name to (query, DuckDB twin)."""
    s = scored_sql("logistic")
    return {
        "risk_squared": _risk("squared"),
        "risk_hinge": _risk("hinge"),
        "risk_logistic": _risk("logistic"),
        "zero_one_error": (zero_one, f"WITH {s} SELECT round(avg(CASE WHEN (s >= 0) = (label > 0) THEN 0.0 ELSE 1.0 END), 6) AS error FROM sc"),
        "objective_l1": _objective("l1"),
        "objective_l2": _objective("l2"),
        "full_gradient_step": (gradient_step, f"WITH {s} SELECT {', '.join(f'round(avg(slope * {c}), 6) + 0.0 AS g_{c}' for c in FEATURES)} FROM sc"),
        "full_gradient_descent_10": (descent_10, descent_sql()),
        "row_lengths_top20": (lengths_top20, f"WITH {s} SELECT instance_id, round(len, 6) AS len FROM sc ORDER BY len DESC, instance_id LIMIT 20"),
        "uncertainty_significance": _gain("entropy", 50),
        "infogain_pick": _gain("entropy", 1),
        "infogain_expected_length": _gain("expected_length", 50),
        "exact_probabilities": (exact_probabilities, f"WITH {s}, t AS (SELECT len / sum(len) OVER () AS p FROM sc) SELECT round(sum(p), 6) AS sum_p, round(max(p) * 1e6, 4) AS max_p_millionths, round(stddev_pop(p) * 1e6, 4) AS std_p_millionths, count(*) FILTER (WHERE p > 0) AS positive FROM t"),
        "history_probabilities_beta": (history_probabilities, f"WITH {STORED_SQL} SELECT instance_id, round(({1 - BETA} * magnitude / sum(magnitude) OVER () + {BETA} / count(*) OVER ()) * 1e6, 3) AS prob_millionths FROM stored ORDER BY 2 DESC, 1 LIMIT 50"),
        "floor_check": (floor_check, f"WITH {STORED_SQL}, p AS (SELECT {1 - BETA} * magnitude / sum(magnitude) OVER () + {BETA} / count(*) OVER () AS p FROM stored) SELECT round(min(p) * count(*), 6) AS least_np, round(sum(p), 6) AS sum_p, min(p) * count(*) >= {BETA} AS floor_holds FROM p"),
        "variance_uniform_weighted_optimal": (variance_report, _variance_sql(1)),
        "variance_batch": (lambda a, b: variance_report(a, b, 128), _variance_sql(128)),
        "equivalent_batch": (equivalent_batch, EQUIV_SQL),
        "unbiasedness_gap": (unbiasedness, "SELECT 0.0::DOUBLE AS bias_norm"),
        "biased_objective": (lambda a, b: unbiasedness(a, b, False), BIASED_SQL),
        "equal_step_length": (equal_lengths, f"WITH {s} SELECT round(avg(len), 6) AS least, round(avg(len), 6) AS greatest, round(avg(len), 6) AS mean_length FROM sc"),
        "uniform_draw_128": (uniform_draw, _draw_sql(1, flat=True)),
        "weighted_draw_128": (weighted_draw, _draw_sql(1)),
        "mixture_draw": (mixture, _draw_sql(2, mix=True)),
        "visit_counts": (visit_counts, f"WITH {VISITS_SQL} SELECT instance_id, visits, last_step FROM vis ORDER BY visits DESC, instance_id LIMIT 20"),
        "staleness_report": (staleness_report, f"WITH {VISITS_SQL}, a AS (SELECT s.instance_id, v.visits, 40 - coalesce(v.last_step, 0) AS age FROM stored s LEFT JOIN vis v USING (instance_id)) SELECT count(visits) AS visited, round(avg(age), 6) AS mean_age, round(avg(age) FILTER (WHERE visits IS NOT NULL), 6) AS mean_age_visited, quantile_cont(age, 0.5) FILTER (WHERE visits IS NOT NULL) AS median_age_visited, quantile_cont(age, 0.9) FILTER (WHERE visits IS NOT NULL) AS p90_age_visited, max(age)::BIGINT AS max_age, sum(visits)::BIGINT AS draws FROM a"),
        "poisson_draw": (poisson, _poisson_sql()),
        "subset_without_replacement": (subset, f"WITH {INST} SELECT instance_id, round({uniform_sql(str(SEED), '1', 'instance_id')}, 9) AS u FROM inst ORDER BY {uniform_sql(str(SEED), '1', 'instance_id')}, instance_id LIMIT 200"),
        "subset_by_threshold": (subset_large, f"WITH {INST} SELECT instance_id, round({uniform_sql(str(SEED), '1', 'instance_id')}, 9) AS u FROM inst ORDER BY {uniform_sql(str(SEED), '1', 'instance_id')}, instance_id LIMIT 200"),
        "exponential_key_preview": (preview, f"WITH {STORED_SQL}, k AS (SELECT instance_id, -ln({uniform_sql(str(SEED), 'instance_id')}) / magnitude AS key FROM stored) SELECT instance_id, round(key * 1e6, 3) AS key_millionths FROM k ORDER BY key LIMIT 100"),
        "holdout_risk": (holdout_risk, f"WITH {s} SELECT count(*) AS rows, round(avg(loss), 6) AS risk, round(avg(CASE WHEN (s >= 0) = (label > 0) THEN 0.0 ELSE 1.0 END), 6) AS error FROM sc WHERE {uniform_sql('split', 'instance_id')} < 0.2"),
        "class_probability": (class_probability, f"WITH {s}, q AS (SELECT label, 1.0 / (1.0 + exp(-(s * label))) AS p FROM sc) SELECT label::INTEGER AS label, round(avg(p), 6) AS p, round(avg(CASE WHEN p > 0 AND p < 1 THEN -p * ln(p) - (1 - p) * ln(1 - p) ELSE 0 END), 6) AS entropy, count(*) FILTER (WHERE p > 0.5) AS right FROM q GROUP BY 1"),
        "stage_and_length_costs": (stage_and_length_costs, "WITH n AS (SELECT count(*) // 16 AS n FROM lineitem) SELECT n AS rows, round(1.0 - n / ((16 * n // 128) * 128.0), 6) AS benefit, round(96.0 / 2048, 6) AS length_cost FROM n"),
        "shard_masses": (shard_masses, f"WITH {STORED_SQL} SELECT shard, count(*) AS rows, round(sum(magnitude), 6) AS mass FROM stored GROUP BY shard"),
        "two_level_vs_global": (two_level_vs_global, "SELECT 64::BIGINT AS draws, 64::BIGINT AS same"),
        "proximal_stage_objective": (proximal, PROXIMAL_SQL),
        "softmax_lengths": (softmax_lengths, _softmax_sql()),
        "layer_norm_factorised": (softmax_lengths, _softmax_sql()),
        "layer_norm_bruteforce": (softmax_bruteforce, _softmax_sql()),
        "pca_lengths": (pca_lengths, _pca_sql()),
        "uniform_minibatch_step": _one_step("uniform"),
        "exact_weighted_step": _one_step("exact"),
        "history_step_and_state": _one_step("history"),
        "train_uniform_short": (_short("uniform"), _short_sql("uniform")),
        "train_history_short": (_short("history"), _short_sql("history")),
        "train_staged_short": (staged_short, _staged_sql()),
    }
