"""Relational surround of the trainers: features, joins, aggregates, windows, sets, subqueries.

Each entry is (query, DuckDB twin); a twin of None marks results that SQL can't state exactly
(sketches, samples).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import columns as C
from ..functions import features as X
from ..sources.tables import read_table, register_views

TARGETS = "step int, shard int, target double"


def _t(s: SparkSession, d: str, name: str, *cols: str) -> DataFrame:
    return read_table(s, d, name, list(cols) or None)


def _visits(s: SparkSession, d: str) -> DataFrame:
    """Stand-in draws: events name rows (users) at steps (hours)."""
    ev = _t(s, d, "events", "event_id", "ts", "user_id", "event_type", "value")
    return ev.withColumn("step", (F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).cast("long"))


VISITS = "visits AS (SELECT event_id, ts, user_id, event_type, value, CAST(floor(epoch(ts) / 3600) AS BIGINT) AS step FROM events)"


def project_features(s, d):
    return X.net_price(s, d).select("instance_id", *[F.round(c, 6).alias(c) for c in ("x1", "x2", "x3", "x4")], "label")


def filter_predicates(s, d):
    li = _t(s, d, "lineitem", "l_quantity", "l_returnflag", "l_linestatus", "l_shipdate", "l_discount")
    keep = F.col("l_quantity").between(10, 30) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").eqNullSafe("O") & (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz")) & F.col("l_returnflag").rlike("^[AR]$") & F.col("l_discount").isNotNull()
    return li.where(keep).groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_discount"), 4).alias("discount"))


def scalar_math(s, d):
    p = _t(s, d, "part", "p_partkey", "p_retailprice", "p_size")
    x = F.col("p_retailprice") / 1000
    return p.select("p_partkey", F.round(C.sigmoid(x - 1), 6).alias("sig"), F.round(F.log1p(x), 6).alias("l"), F.round(F.sqrt(x), 6).alias("r"), F.round(F.pow(x, 1.5), 6).alias("p"), F.signum(F.col("p_size") - 25.0).alias("sg"), F.floor(x).alias("f"), F.ceil(x).alias("c"), F.greatest("p_size", F.lit(10)).alias("g"), F.pmod(-F.col("p_size"), F.lit(7)).cast("int").alias("m"))


def scalar_string(s, d):
    c = _t(s, d, "customer", "c_custkey", "c_name", "c_mktsegment")
    return c.select("c_custkey", F.lower("c_mktsegment").alias("seg"), F.regexp_extract("c_name", r"(\d+)", 1).alias("digits"), F.regexp_replace("c_name", r"\d", "0").alias("masked"), F.concat_ws("/", F.substring("c_mktsegment", 1, 3), F.length("c_name").cast("string")).alias("tag"), F.md5("c_name").alias("h"))


def scalar_date(s, d):
    o = _t(s, d, "orders", "o_orderkey", "o_orderdate")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", "o_orderdate").cast("date").alias("start"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("days"), F.date_add(F.col("o_orderdate").cast("date"), 30).alias("due"))


def array_math(s, d):
    e = _t(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    shifted = F.concat(F.slice("x", 64, 1), F.slice("x", 1, 63))
    top = F.array_position("x", F.array_max("x"))
    return e.select("vec_id", F.round(C.array_dot(F.col("x"), F.col("x")), 5).alias("sq"), F.round(C.array_dot(F.col("x"), shifted), 6).alias("turned"), top.cast("int").alias("top"), F.round(F.aggregate(F.transform("x", lambda v, i: v * i), F.lit(0.0), lambda a, v: a + v), 5).alias("ramp"))


def map_sparse(s, d):
    long = X.token_buckets(_t(s, d, "benchmark", "item_id", "text"), "item_id", "text", 256)
    return long.select("item_id", F.col("feature").cast("long").alias("feature"), F.round("value", 6).alias("value"))


BUCKET_SQL = """tok AS (SELECT {key} AS k, unnest(list_filter(regexp_split_to_array(lower({text}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')) AS w FROM {table}),
cnt AS (SELECT k, ('0x' || substr(md5(w), 1, 8))::BIGINT % {b} AS feature, count(*)::DOUBLE AS n FROM tok GROUP BY ALL),
sp AS (SELECT k, feature, n / sqrt(sum(n * n) OVER (PARTITION BY k)) AS value FROM cnt)"""


def hash_text_features(s, d):
    docs = _t(s, d, "documents", "doc_id", "text").join(_t(s, d, "labels", "doc_id"), "doc_id", "left_semi")
    long = X.token_buckets(docs, "doc_id", "text", 256)
    return long.groupBy("feature").agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("value"), 4).alias("mass")).select(F.col("feature").cast("long").alias("feature"), "rows", "mass")


def json_props(s, d):
    ev = _t(s, d, "events", "event_type", "props", "value")
    k = F.from_json("props", "k int")["k"]
    return ev.groupBy("event_type").agg(F.sum(k.cast("long")).alias("k_sum"), F.count(k).alias("k_n"), F.max(F.get_json_object("props", "$.k").cast("int")).alias("k_max"))


def url_features(s, d):
    p = _t(s, d, "pages", "page_id", "url", "html")
    return p.select("page_id", F.regexp_extract("url", r"^(\w+)://", 1).alias("scheme"), F.regexp_extract("url", r"://([^/?#]+)", 1).alias("host"), F.size(F.split("url", "/")).cast("int").alias("parts"), F.length("html").cast("int").alias("html_length"), F.length(F.regexp_replace("html", r"<[^>]*>", "")).cast("int").alias("text_length"))


def event_features(s, d):
    ev = X.event_values(s, d)
    return ev.agg(F.round(F.avg("hour"), 6).alias("hour"), *[F.sum(f"is_{t}").cast("long").alias(f"is_{t}") for t in ("click", "purchase", "search", "signup", "view")], F.round(F.avg("k"), 6).alias("k"), F.round(F.avg("label"), 4).alias("value"))


def standardise(s, d):
    return X.net_price(s, d).agg(*[F.round(F.stddev_pop(c), 6).alias(f"std_{c}") for c in ("x1", "x2", "x3", "x4")], F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("label") > 0, 1)).alias("positive"))


def split_and_shard(s, d):
    own = X.as_instances(X.net_price(s, d), ["x1", "x2", "x3", "x4", "x0"])
    return own.groupBy("shard").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("is_valid"), 1)).alias("valid"))


def join_draws_instances(s, d):
    drawn = _t(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100)
    return _t(s, d, "lineitem", "l_orderkey", "l_quantity").join(F.broadcast(drawn), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("rows"), F.sum("l_quantity").alias("quantity"))


def join_history_left(s, d):
    seen = _visits(s, d).groupBy("user_id").agg(F.max_by("value", F.struct("step", "event_id")).alias("magnitude"))
    c = _t(s, d, "customer", "c_custkey")
    return c.join(seen, c.c_custkey == seen.user_id, "left").select("c_custkey", F.round(F.coalesce("magnitude", F.lit(1.0)), 4).alias("magnitude"))


def _star(s, d, hint):
    li = _t(s, d, "lineitem", "l_orderkey", "l_extendedprice")
    o = _t(s, d, "orders", "o_orderkey", "o_custkey").hint(hint)
    c = _t(s, d, "customer", "c_custkey", "c_mktsegment").hint(hint)
    return li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


STAR_SQL = "SELECT c_mktsegment, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1"


def join_stage_semi(s, d):
    own = X.net_price(s, d).select("instance_id", "x1", "label")
    few = own.select("instance_id", C.hash_uniform(7, 1, F.col("instance_id")).alias("u")).where("u < 0.05")
    return own.join(few, "instance_id", "left_semi").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("label"), 4).alias("label"))


def join_unvisited_anti(s, d):
    c = _t(s, d, "customer", "c_custkey", "c_nationkey")
    return c.join(_visits(s, d), F.col("c_custkey") == F.col("user_id"), "left_anti").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("never"))


def join_range_cdf(s, d):
    """Targets placed in running-sum intervals: an equi-join on the shard with the range as residual."""
    p = _t(s, d, "part", "p_partkey", "p_size").select("p_partkey", F.pmod("p_partkey", F.lit(4)).cast("int").alias("shard"), F.col("p_size").cast("long").alias("m"))
    hi = F.sum("m").over(Window.partitionBy("shard").orderBy("p_partkey"))
    targets = s.createDataFrame([(j, j % 4, float(j * 7 % 997) + 0.5) for j in range(200)], TARGETS)
    run = p.withColumn("hi", hi)
    hit = (run.shard == targets.shard) & (targets.target < run.hi) & (targets.target >= run.hi - run.m)
    return run.join(F.broadcast(targets), hit).select("step", "p_partkey", F.col("hi").alias("hi"))


def join_theta_pairs(s, d):
    """Variance from the gaps of all pairs of rows, without the pairs: sums give their mean square."""
    v = F.col("s_acctbal")
    sums = _t(s, d, "supplier", "s_acctbal").where(v.isNotNull()).agg(F.count(F.lit(1)).alias("n"), F.sum(v).alias("s1"), F.sum(v * v).alias("s2"))
    n = F.col("n")
    return sums.select((n * (n - 1) / 2).cast("long").alias("pairs"), F.round((n * F.col("s2") - F.col("s1") * F.col("s1")) / (n * n), 2).alias("variance"))


def join_cross_augment(s, d):
    e = _t(s, d, "embeddings", "vec_id", "embedding", "label")
    wide = e.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"), F.explode(F.sequence(F.lit(0), F.lit(127))).alias("copy"))
    first = F.get("x", F.pmod(-F.col("copy"), F.lit(64)))  # what a cyclic shift by `copy` brings to the front
    return wide.groupBy("label", F.pmod("copy", F.lit(4)).alias("turn")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(first), 4).alias("front"))


def join_asof_history(s, d):
    """Last visit of the same row at or before each purchase, by one window over the union."""
    v = _visits(s, d)
    own = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = v.withColumn("prev", F.last(F.when(F.col("event_type") == "click", F.col("value")), ignorenulls=True).over(own))
    return seen.where("event_type = 'purchase'").select("event_id", F.round("prev", 4).alias("prev"))


def join_interval_events(s, d):
    v = _visits(s, d)
    a = v.where("event_type = 'click'").select("user_id", F.col("ts").alias("t1"))
    b = v.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    near = (a.user_id == b.u2) & (b.t2 >= a.t1) & (b.t2 <= a.t1 + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, near).groupBy("user_id").agg(F.count(F.lit(1)).alias("pairs"))


def join_full_outer_visits(s, d):
    v = _visits(s, d)
    a = v.where("event_type = 'click'").groupBy("user_id").agg(F.count(F.lit(1)).alias("a"))
    b = v.where("event_type = 'signup'").groupBy("user_id").agg(F.count(F.lit(1)).alias("b"))
    return a.join(b, "user_id", "full").select("user_id", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))


def join_sparse_model(s, d):
    long = X.token_buckets(_t(s, d, "benchmark", "item_id", "text"), "item_id", "text", 256)
    w = s.range(256).select(F.col("id").alias("feature"), ((F.col("id") % 7) - 3.0).alias("w"))
    return long.join(F.broadcast(w), "feature").groupBy("item_id").agg(F.round(F.sum(F.col("value") * F.col("w")), 6).alias("score"))


def _own(s, d):
    from ..plans.theory import scored

    return scored(s, d)


def agg_loss_partial_final(s, d):
    return _own(s, d).agg(F.round(F.sum("loss"), 4).alias("loss"), F.round(F.sum("len"), 4).alias("len"), F.round(F.sum(F.col("len") * F.col("len")), 4).alias("len2"), F.count(F.lit(1)).alias("n"))


def agg_gradient_coordinates(s, d):
    long = _own(s, d).select("slope", F.posexplode(F.array("x1", "x2", "x3", "x4", "x0")))
    return long.groupBy("pos").agg(F.round(F.sum(F.col("slope") * F.col("col")), 4).alias("g"))


def agg_sort_based(s, d):
    v = _visits(s, d).where("event_type = 'signup'")
    return v.groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_list("event_id")), ",").alias("ids"))


def agg_distinct(s, d):
    return _visits(s, d).groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("user_id", "step").alias("user_steps"))


def agg_approx(s, d):
    return _visits(s, d).groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", [0.5, 0.9]).alias("q"))


def agg_max_by_latest(s, d):
    return _visits(s, d).groupBy("user_id").agg(F.max_by("value", F.struct("ts", "event_id")).alias("value"), F.max("step").alias("last_step"))


def _errors(s, d):
    li = _t(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_extendedprice", "l_discount")
    wrong = (F.col("l_extendedprice") > 52000) != (F.col("l_extendedprice") * (1 - F.col("l_discount")) > 50000)
    return li.select("l_returnflag", "l_linestatus", wrong.cast("int").alias("wrong"))


ERR = "err AS (SELECT l_returnflag, l_linestatus, CAST((l_extendedprice > 52000) <> (l_extendedprice * (1 - l_discount) > 50000) AS INTEGER) AS wrong FROM lineitem)"
ERR_OUT = "l_returnflag, l_linestatus, grouping(l_returnflag) * 2 + grouping(l_linestatus) AS g, count(*) AS n, sum(wrong)::BIGINT AS wrong"


def _grouped(how):
    def q(s, d):
        if how == "sets":
            _errors(s, d).createOrReplaceTempView("_errors")
            return s.sql("SELECT l_returnflag, l_linestatus, grouping_id() AS g, count(*) AS n, sum(wrong) AS wrong FROM _errors GROUP BY l_returnflag, l_linestatus GROUPING SETS ((l_returnflag), (l_linestatus), ())")
        return getattr(_errors(s, d), how)("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"), F.sum("wrong").alias("wrong"))

    clause = {"rollup": "ROLLUP (l_returnflag, l_linestatus)", "cube": "CUBE (l_returnflag, l_linestatus)", "sets": "GROUPING SETS ((l_returnflag), (l_linestatus), ())"}[how]
    return q, f"WITH {ERR} SELECT {ERR_OUT} FROM err GROUP BY {clause}"


def agg_pivot_confusion(s, d):
    own = _own(s, d).select(F.col("label").cast("int").alias("label"), F.when(F.col("score") >= 0, "pos").otherwise("neg").alias("predicted"))
    return own.groupBy("label").pivot("predicted", ["pos", "neg"]).count().na.fill(0)


def agg_filter_clause(s, d):
    register_views(s, d)
    return s.sql("SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, count(*) FILTER (WHERE value <= 50) AS low FROM events GROUP BY event_type")


def agg_statistics(s, d):
    return _own(s, d).agg(F.round(F.stddev_samp("len"), 6).alias("sd"), F.round(F.var_pop("len"), 6).alias("var"), F.round(F.corr("len", "loss"), 6).alias("corr"), F.round(F.covar_pop("len", "loss"), 6).alias("cov"))


def agg_histogram(s, d):
    ev = _t(s, d, "events", "value")
    return ev.groupBy(F.least(F.floor(F.col("value") / 25), F.lit(20)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def _by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


def window_running_mass(s, d):
    run = F.sum("value").over(_by_user().rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return _visits(s, d).select("event_id", F.round(run, 4).alias("mass"))


def window_rank_lengths(s, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey")
    return _t(s, d, "supplier").select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


def window_visit_interval(s, d):
    return _visits(s, d).select("event_id", (F.col("step") - F.lag("step").over(_by_user())).alias("since"))


def window_moving_loss(s, d):
    daily = _visits(s, d).groupBy(F.to_date("ts").alias("day")).agg(F.avg("value").alias("v"))  # a trace: one row a day
    return daily.select("day", F.round(F.avg("v").over(Window.orderBy("day").rowsBetween(-9, 0)), 6).alias("moving"))


def window_time_range(s, d):
    v = _visits(s, d).withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return v.select("event_id", F.round(F.avg("value").over(w), 5).alias("day_mean"), F.count(F.lit(1)).over(w).alias("n"))


def window_first_last(s, d):
    w = _by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _visits(s, d).select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 2).over(w).alias("second"))


def _top(asc: bool, k: int):
    def q(s, d):
        key = F.col("o_totalprice").asc() if asc else F.col("o_totalprice").desc()
        return _t(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(key, "o_orderkey").limit(k)

    return q, f"SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice {'ASC' if asc else 'DESC'}, o_orderkey LIMIT {k}"


def topk_per_group(s, d):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(s, d, "orders", "o_orderkey", "o_orderpriority", "o_totalprice").withColumn("rn", F.row_number().over(w)).where("rn <= 5").select("o_orderpriority", "o_orderkey", "rn")


def sort_total(s, d):
    return _t(s, d, "nation", "n_nationkey", "n_name").orderBy(F.desc("n_name")).select("n_nationkey", "n_name")


def limit_offset(s, d):
    return _t(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20)


def _sets(how):
    def q(s, d):
        v = _visits(s, d)
        a, b = v.where("event_type = 'click'").select("user_id"), v.where("event_type = 'purchase'").select("user_id")
        out = {"union_all": lambda: a.unionByName(b), "union_distinct": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[how]()
        return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))

    word = {"union_all": "UNION ALL", "union_distinct": "UNION", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}[how]
    return q, f"SELECT user_id, count(*) AS n FROM (SELECT user_id FROM events WHERE event_type = 'click' {word} SELECT user_id FROM events WHERE event_type = 'purchase') GROUP BY user_id"


def _sql(text: str):
    def q(s, d):
        register_views(s, d)
        return s.sql(text)

    return q, text


def unpivot_trace(s, d):
    wide = _own(s, d).agg(F.round(F.avg("loss"), 6).alias("loss"), F.round(F.avg("len"), 6).alias("length")).withColumn("step", F.lit(1))
    return wide.unpivot("step", ["loss", "length"], "measure", "value")


def queries() -> dict[str, tuple]:
    from ..plans.theory import INST, SHARD_SQL, scored_sql, uniform_sql

    sc = scored_sql("logistic")
    w = "PARTITION BY user_id ORDER BY ts, event_id"
    sparse = BUCKET_SQL.format(key="item_id", text="text", table="benchmark", b=256)
    return {
        "project_features": (project_features, f"WITH {INST} SELECT instance_id, round(x1, 6) AS x1, round(x2, 6) AS x2, round(x3, 6) AS x3, round(x4, 6) AS x4, label FROM inst"),
        "filter_predicates": (filter_predicates, "SELECT l_returnflag, count(*) AS n, round(sum(l_discount), 4) AS discount FROM lineitem WHERE l_quantity BETWEEN 10 AND 30 AND l_returnflag IN ('A', 'R') AND l_linestatus IS NOT DISTINCT FROM 'O' AND l_shipdate >= TIMESTAMP '1995-01-01' GROUP BY 1"),
        "scalar_math": (scalar_math, "SELECT p_partkey, round(1 / (1 + exp(1 - p_retailprice / 1000)), 6) AS sig, round(ln(1 + p_retailprice / 1000), 6) AS l, round(sqrt(p_retailprice / 1000), 6) AS r, round(pow(p_retailprice / 1000, 1.5), 6) AS p, sign(p_size - 25)::DOUBLE AS sg, floor(p_retailprice / 1000)::BIGINT AS f, ceil(p_retailprice / 1000)::BIGINT AS c, greatest(p_size, 10)::INTEGER AS g, ((7 - p_size % 7) % 7)::INTEGER AS m FROM part"),
        "scalar_string": (scalar_string, "SELECT c_custkey, lower(c_mktsegment) AS seg, regexp_extract(c_name, '(\\d+)', 1) AS digits, regexp_replace(c_name, '\\d', '0', 'g') AS masked, substr(c_mktsegment, 1, 3) || '/' || length(c_name) AS tag, md5(c_name) AS h FROM customer"),
        "scalar_date": (scalar_date, "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_trunc('month', o_orderdate)::DATE AS start, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, (o_orderdate::DATE + 30)::DATE AS due FROM orders"),
        "array_math": (array_math, "WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings) SELECT vec_id, round(list_dot_product(x, x), 5) AS sq, round(list_dot_product(x, list_concat(x[64:64], x[1:63])), 6) AS turned, list_position(x, list_max(x))::INTEGER AS top, round(list_sum(list_transform(x, lambda v, i: v * (i - 1))), 5) AS ramp FROM e"),
        "map_sparse": (map_sparse, f"WITH {sparse} SELECT k AS item_id, feature, round(value, 6) AS value FROM sp"),
        "hash_text_features": (hash_text_features, f"WITH {BUCKET_SQL.format(key='doc_id', text='text', table='(SELECT * FROM documents WHERE doc_id IN (SELECT doc_id FROM labels))', b=256)} SELECT feature, count(*) AS rows, round(sum(value), 4) AS mass FROM sp GROUP BY 1"),
        "json_props": (json_props, "SELECT event_type, sum((props->>'$.k')::INTEGER)::BIGINT AS k_sum, count(props->>'$.k') AS k_n, max((props->>'$.k')::INTEGER) AS k_max FROM events GROUP BY 1"),
        "url_features": (url_features, "SELECT page_id, regexp_extract(url, '^(\\w+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host, len(string_split(url, '/'))::INTEGER AS parts, length(html)::INTEGER AS html_length, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INTEGER AS text_length FROM pages"),
        "event_features": (event_features, "SELECT round(avg(hour(ts) / 24.0), 6) AS hour, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS is_{t}" for t in ("click", "purchase", "search", "signup", "view")) + ", round(avg((props->>'$.k')::DOUBLE), 6) AS k, round(avg(value), 4) AS value FROM events"),
        "standardise": (standardise, f"WITH {INST} SELECT {', '.join(f'round(stddev_pop({c}), 6) AS std_{c}' for c in ('x1', 'x2', 'x3', 'x4'))}, count(*) AS n, count(*) FILTER (WHERE label > 0) AS positive FROM inst"),
        "split_and_shard": (split_and_shard, f"WITH {INST} SELECT {SHARD_SQL} AS shard, count(*) AS n, count(*) FILTER (WHERE {uniform_sql('split', 'instance_id')} < 0.2) AS valid FROM inst GROUP BY 1"),
        "join_draws_instances": (join_draws_instances, "SELECT o_orderkey, count(*) AS rows, sum(l_quantity) AS quantity FROM lineitem JOIN (SELECT * FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100) ON l_orderkey = o_orderkey GROUP BY 1"),
        "join_history_left": (join_history_left, f"WITH {VISITS}, h AS (SELECT user_id, arg_max(value, (step, event_id)) AS m FROM visits GROUP BY 1) SELECT c_custkey, round(coalesce(m, 1.0), 4) AS magnitude FROM customer LEFT JOIN h ON c_custkey = user_id"),
        "join_shuffle_hash": (lambda s, d: _star(s, d, "shuffle_hash"), STAR_SQL),
        "join_sort_merge": (lambda s, d: _star(s, d, "merge"), STAR_SQL),
        "join_stage_semi": (join_stage_semi, f"WITH {INST} SELECT count(*) AS n, round(sum(label), 4) AS label FROM inst WHERE {uniform_sql('7', '1', 'instance_id')} < 0.05"),
        "join_unvisited_anti": (join_unvisited_anti, "SELECT c_nationkey, count(*) AS never FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events WHERE user_id IS NOT NULL) GROUP BY 1"),
        "join_range_cdf": (join_range_cdf, "WITH p AS (SELECT p_partkey, (p_partkey % 4)::INTEGER AS shard, p_size::BIGINT AS m, sum(p_size::BIGINT) OVER (PARTITION BY p_partkey % 4 ORDER BY p_partkey) AS hi FROM part), t AS (SELECT j AS step, (j % 4) AS shard, (j * 7 % 997) + 0.5 AS target FROM range(200) r(j)) SELECT step::INTEGER AS step, p_partkey, hi::BIGINT AS hi FROM p JOIN t ON p.shard = t.shard AND target < hi AND target >= hi - m"),
        "join_theta_pairs": (join_theta_pairs, "WITH a AS (SELECT s_suppkey, s_acctbal FROM supplier) SELECT count(*) AS pairs, round(sum(pow(x.s_acctbal - y.s_acctbal, 2)) / pow((SELECT count(*) FROM a), 2), 2) AS variance FROM a x JOIN a y ON x.s_suppkey < y.s_suppkey"),
        "join_cross_augment": (join_cross_augment, "SELECT label, (c % 4)::INTEGER AS turn, count(*) AS n, round(sum(embedding[((64 - c % 64) % 64) + 1]::DOUBLE), 4) AS front FROM embeddings, range(128) r(c) GROUP BY 1, 2"),
        "join_asof_history": (join_asof_history, f"WITH {VISITS}, s AS (SELECT *, last_value(CASE WHEN event_type = 'click' THEN value END IGNORE NULLS) OVER ({w} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM visits) SELECT event_id, round(prev, 4) AS prev FROM s WHERE event_type = 'purchase'"),
        "join_interval_events": (join_interval_events, "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase' GROUP BY 1"),
        "join_full_outer_visits": (join_full_outer_visits, "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS a, count(*) FILTER (WHERE event_type = 'signup') AS b FROM events WHERE event_type IN ('click', 'signup') GROUP BY 1"),
        "join_sparse_model": (join_sparse_model, f"WITH {sparse} SELECT k AS item_id, round(sum(value * (feature % 7 - 3.0)), 6) AS score FROM sp GROUP BY 1"),
        "agg_loss_partial_final": (agg_loss_partial_final, f"WITH {sc} SELECT round(sum(loss), 4) AS loss, round(sum(len), 4) AS len, round(sum(len * len), 4) AS len2, count(*) AS n FROM sc"),
        "agg_gradient_coordinates": (agg_gradient_coordinates, f"WITH {sc} " + " UNION ALL ".join(f"SELECT {i} AS pos, round(sum(slope * {c}), 4) AS g FROM sc" for i, c in enumerate(("x1", "x2", "x3", "x4", "x0")))),
        "agg_sort_based": (agg_sort_based, "SELECT user_id, string_agg(event_id::VARCHAR, ',' ORDER BY event_id) AS ids FROM events WHERE event_type = 'signup' GROUP BY 1"),
        "agg_distinct": (agg_distinct, f"WITH {VISITS} SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT (user_id, step)) AS user_steps FROM visits GROUP BY 1"),
        "agg_approx": (agg_approx, None),
        "agg_max_by_latest": (agg_max_by_latest, f"WITH {VISITS} SELECT user_id, arg_max(value, (ts, event_id)) AS value, max(step) AS last_step FROM visits GROUP BY 1"),
        "agg_rollup_error": _grouped("rollup"),
        "agg_cube_error": _grouped("cube"),
        "agg_grouping_sets": _grouped("sets"),
        "agg_pivot_confusion": (agg_pivot_confusion, f"WITH {sc} SELECT label::INTEGER AS label, count(*) FILTER (WHERE s >= 0) AS pos, count(*) FILTER (WHERE s < 0) AS neg FROM sc GROUP BY 1"),
        "agg_filter_clause": (agg_filter_clause, "SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, count(*) FILTER (WHERE value <= 50) AS low FROM events GROUP BY 1"),
        "agg_statistics": (agg_statistics, f"WITH {sc} SELECT round(stddev_samp(len), 6) AS sd, round(var_pop(len), 6) AS var, round(corr(len, loss), 6) AS corr, round(covar_pop(len, loss), 6) AS cov FROM sc"),
        "agg_histogram": (agg_histogram, "SELECT least(floor(value / 25), 20)::INTEGER AS bin, count(*) AS n FROM events GROUP BY 1"),
        "window_running_mass": (window_running_mass, f"SELECT event_id, round(sum(value) OVER ({w} ROWS UNBOUNDED PRECEDING), 4) AS mass FROM events"),
        "window_rank_lengths": (window_rank_lengths, "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey)"),
        "window_visit_interval": (window_visit_interval, f"WITH {VISITS} SELECT event_id, step - lag(step) OVER ({w}) AS since FROM visits"),
        "window_moving_loss": (window_moving_loss, "WITH t AS (SELECT ts::DATE AS day, avg(value) AS v FROM events GROUP BY 1) SELECT day, round(avg(v) OVER (ORDER BY day ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 6) AS moving FROM t"),
        "window_time_range": (window_time_range, "WITH t AS (SELECT *, floor(epoch(ts))::BIGINT AS sec FROM events) SELECT event_id, round(avg(value) OVER w, 5) AS day_mean, count(*) OVER w AS n FROM t WINDOW w AS (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)"),
        "window_first_last": (window_first_last, f"SELECT event_id, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS ({w} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
        "topk_lengths": _top(False, 25),
        "bottomk_lengths": _top(True, 25),
        "topk_per_group": (topk_per_group, "SELECT o_orderpriority, o_orderkey, rn FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 5"),
        "sort_total": (sort_total, "SELECT n_nationkey, n_name FROM nation ORDER BY n_name DESC"),
        "limit_offset": (limit_offset, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10"),
        **{f"set_{h}": _sets(h) for h in ("union_all", "union_distinct", "intersect", "intersect_all", "except", "except_all")},
        "subquery_scalar": _sql("SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_extendedprice > (SELECT avg(l_extendedprice) FROM lineitem) GROUP BY l_returnflag"),
        "subquery_exists": _sql("SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_discount > 0.08) GROUP BY o_orderpriority"),
        "subquery_correlated": _sql("SELECT count(*) AS n FROM lineitem a WHERE a.l_extendedprice = (SELECT max(b.l_extendedprice) FROM lineitem b WHERE b.l_orderkey = a.l_orderkey)"),
        "cte_chain": _sql("WITH a AS (SELECT user_id, count(*) AS n FROM events GROUP BY user_id), b AS (SELECT n, count(*) AS users FROM a GROUP BY n) SELECT n, users FROM b WHERE users > 1"),
        "cte_recursive": _sql("WITH RECURSIVE g AS (SELECT l_returnflag, CAST(avg(l_discount) AS DOUBLE) AS goal FROM lineitem GROUP BY l_returnflag), t(l_returnflag, goal, k, w) AS (SELECT l_returnflag, goal, 1, CAST(0.0 AS DOUBLE) FROM g UNION ALL SELECT l_returnflag, goal, k + 1, CAST(w + 0.5 * (goal - w) AS DOUBLE) FROM t WHERE k < 12) SELECT l_returnflag, k, round(w, 9) AS w FROM t"),
        "unpivot_trace": (unpivot_trace, f"WITH {sc} SELECT 1 AS step, 'loss' AS measure, round(avg(loss), 6) AS value FROM sc UNION ALL SELECT 1, 'length', round(avg(len), 6) FROM sc"),
        "sample_fraction": (lambda s, d: _t(s, d, "orders", "o_orderkey").sample(0.1, seed=3), None),
        "sample_by_class": (lambda s, d: _t(s, d, "orders", "o_orderkey", "o_orderpriority").sampleBy("o_orderpriority", {"1-URGENT": 0.2, "5-LOW": 0.05}, seed=3), None),
    }
