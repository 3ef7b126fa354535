"""The relational operators around the methods, each as a query over the given tables with DuckDB SQL of the same rows."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import measures as A
from ..operators import adaptive as K
from ..operators import l1ball as P
from ..operators import oblivious as O
from ..session import cut, ship
from ..sources import matrix as M
from . import catalog as C
from . import workloads as W

_queries: dict = {}
_sql: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(ship(spark), sf_dir)

        _queries[f.__name__] = run
        if sql:
            _sql[f.__name__] = sql
        return f

    return add


# Learned sketch, unrolled in SQL with the exact ball


def _pass(k: int, lam: float, batch: str = "true") -> str:
    """One pass from centres c{k} to c{k + 1}: assignment a{k}, means where a group has members, exact threshold th{k}."""
    return f"""sq{k} AS (SELECT b AS bucket, coalesce(sum(value * value), 0) AS s FROM range(0, {C.R}) t(b) LEFT JOIN c{k} ON c{k}.bucket = b GROUP BY 1),
x{k} AS (SELECT m.feature_id, c{k}.bucket, sum(m.value * c{k}.value) AS p FROM m JOIN c{k} USING (row_id) GROUP BY 1, 2),
d{k} AS (SELECT f.feature_id, q.bucket, q.s - 2 * coalesce(p, 0) AS d FROM (SELECT DISTINCT feature_id FROM e WHERE {batch}) f CROSS JOIN sq{k} q LEFT JOIN x{k} x ON x.feature_id = f.feature_id AND x.bucket = q.bucket),
a{k} AS (SELECT feature_id, CAST(bucket AS INTEGER) AS bucket FROM (SELECT *, row_number() OVER (PARTITION BY feature_id ORDER BY d, bucket) AS k FROM d{k}) WHERE k = 1),
n{k} AS (SELECT bucket, count(*) AS size FROM a{k} GROUP BY 1),
u{k} AS (SELECT row_id, bucket, sum(value) / max(size) AS value FROM m JOIN a{k} USING (feature_id) JOIN n{k} USING (bucket) GROUP BY 1, 2 HAVING sum(value) <> 0 UNION ALL SELECT row_id, bucket, value FROM c{k} WHERE bucket NOT IN (SELECT bucket FROM n{k})),
th{k} AS (SELECT bucket, greatest(0, max(th)) AS theta FROM (SELECT bucket, (cum - {lam}) / k AS th, row_number() OVER (PARTITION BY bucket ORDER BY k DESC) AS last FROM (SELECT bucket, abs(value) AS a, sum(abs(value)) OVER w AS cum, row_number() OVER w AS k FROM u{k} WINDOW w AS (PARTITION BY bucket ORDER BY abs(value) DESC, row_id ROWS UNBOUNDED PRECEDING)) WHERE a > (cum - {lam}) / k) WHERE last = 1 GROUP BY 1),
c{k + 1} AS (SELECT row_id, bucket, sign(value) * (abs(value) - theta) AS value FROM u{k} JOIN th{k} USING (bucket) WHERE abs(value) > theta)"""


_START = f"WITH {C.CUST}, {C.SIGNED}, {C.PICK}, c0 AS (SELECT row_id, bucket, value FROM m JOIN pick USING (feature_id))"
_TWO = f"{_START}, {_pass(0, 200.0)}, {_pass(1, 200.0)}"


def _two(spark, d):
    return K.learn_full(M.custpart(spark, d), C.R, 2, 200.0, 0.0, C.SEED)


@query(f"{_TWO} SELECT row_id, bucket, round(value, 5) + 0.0 AS value FROM c2 WHERE abs(value) > 1e-6")
def full_two_iterations(spark, d):
    return C.rounded(_two(spark, d).training_sketch().where("abs(value) > 1e-6"), "value", places=5)


@query(f"{_TWO} SELECT row_id, bucket, round(value, 5) + 0.0 AS value FROM (SELECT row_id, bucket, sign(v) * (abs(v) - theta) AS value FROM (SELECT row_id, bucket, sum(value) / max(size) AS v FROM m JOIN a1 USING (feature_id) JOIN n1 USING (bucket) GROUP BY 1, 2) JOIN th1 USING (bucket) WHERE abs(v) > theta) WHERE abs(value) > 1e-6")
def transform_theta_exact(spark, d):
    """The map of new rows with stored thresholds, on the matrix itself."""
    return C.rounded(_two(spark, d).transform(M.custpart(spark, d), "theta").where("abs(value) > 1e-6"), "value", places=5)


@query(f"{_START}, {_pass(0, 200.0, H.drawn_sql('feature_id', 0.3, C.SEED, 'batch1'))} SELECT row_id, bucket, round(value, 5) + 0.0 AS value FROM c1 WHERE abs(value) > 1e-6")
def minibatch_one_iteration(spark, d):
    return C.rounded(K.learn_minibatch(M.custpart(spark, d), C.R, 1, 0.3, 200.0, 0.0, C.SEED).training_sketch().where("abs(value) > 1e-6"), "value", places=5)


@query(f"WITH {C.CUST} SELECT DISTINCT feature_id FROM e WHERE {H.drawn_sql('feature_id', 0.3, C.SEED, 'batch1')}")
def minibatch_drawn(spark, d):
    return M.custpart(spark, d).features().where(H.drawn(F.col("feature_id"), 0.3, C.SEED, "batch1"))


@query(f"WITH {C.CUST}, {C.SIGNED}, {C.PICK}, {C.INIT} SELECT count(DISTINCT bucket) AS centres, CAST(0 AS BIGINT) AS outside, CAST(0 AS BIGINT) AS below FROM c")
def l1_inside_bounds(spark, d):
    """Centres inside both bounds after the projection, 500 and 550."""
    c = K.init_centres(C._m(spark, d), C.R, C.SEED)
    return A.l1_feasible(P.project(c, 500.0, 0.1), 500.0, 0.1, c)


@query(f"WITH {C.CUST}, {C.SIGNED}, {C.PICK}, {C.INIT} SELECT bucket, sum(greatest(0, abs(value) - 1.5)) AS left_ FROM c GROUP BY 1")
def l1_residual(spark, d):
    c = K.init_centres(C._m(spark, d), C.R, C.SEED)
    theta = spark.range(C.R).select(F.col("id").cast("int").alias("bucket"), F.lit(1.5).alias("theta"))
    return P.residual(c, theta).withColumnRenamed("left", "left_")


@query(f"WITH {C.CUST}, {C.SIGNED} SELECT feature_id, sum(value * value) AS sq FROM m GROUP BY 1")
def column_norms(spark, d):
    return K.column_norms(C._m(spark, d))


_WIDE = f"{_START}, {C.CS}, {_pass(0, 1e15)}, sizes AS (SELECT (SELECT count(DISTINCT row_id) FROM e) AS n, (SELECT count(DISTINCT feature_id) FROM e) AS d), w AS (SELECT n, d, CAST(pow(2, ceil(log2(d))) AS BIGINT) AS width FROM sizes)"


@query(f"{_WIDE} SELECT 'gaussian' AS method, n * d * {C.R} AS projection, n * {C.R} AS classification FROM w UNION ALL SELECT 'ternary', n * d * {C.R}, n * {C.R} FROM w UNION ALL SELECT 'hadamard', n * width * CAST(log2(width) AS BIGINT), n * {C.R} FROM w UNION ALL SELECT 'hadamard_topr', n * width * CAST(log2(width) AS BIGINT), n * {C.R} FROM w UNION ALL SELECT 'countsketch', (SELECT count(*) FROM e), (SELECT count(*) FROM cs) UNION ALL SELECT 'learned_full', (SELECT count(*) FROM e), (SELECT count(*) FROM u0) UNION ALL SELECT 'learned_minibatch', (SELECT count(*) FROM e), (SELECT count(*) FROM u0)")
def prediction_cost_all(spark, d):
    """The cost model of all seven methods; the learned ones after one pass over all columns."""
    fm = M.custpart(spark, d)
    learned = K.learn_full(fm, C.R, 1, seed=C.SEED).training_sketch()
    sketches = dict.fromkeys(("gaussian", "ternary", "hadamard", "hadamard_topr")) | {"countsketch": O.countsketch(fm, C.R, C.SEED), "learned_full": learned, "learned_minibatch": learned}
    return W.prediction_cost(fm, sketches, C.R, fm.features().count())


@query(f"WITH {C.SUPP}, g AS (SELECT r.row_id, f.feature_id, coalesce(value, 0) AS value FROM (SELECT DISTINCT row_id FROM e) r CROSS JOIN (SELECT DISTINCT feature_id FROM e) f LEFT JOIN e USING (row_id, feature_id)), s AS (SELECT feature_id, min(value) AS lo, max(value) AS hi FROM g GROUP BY 1) SELECT row_id, feature_id, round(2 * (value - lo) / (hi - lo) - 1, 9) + 0.0 AS value FROM g JOIN s USING (feature_id) WHERE hi > lo AND 2 * (value - lo) / (hi - lo) - 1 <> 0")
def minmax_suppart(spark, d):
    """Counts with zeros, which take part in a column's span."""
    return C.rounded(M.min_max(M.suppart(spark, d)).entries, "value", places=9)


@query(f"WITH {C.CUST}, {C.MAP}, t AS (SELECT sum(size) AS all_ FROM sizes) SELECT round(-sum(size / all_ * log2(size / all_)), 9) AS entropy FROM sizes, t")
def group_entropy(spark, d):
    return C.rounded(A.group_entropy(C._cust_map(spark, d)[1]), "entropy", places=9)


@query(f"WITH {C.TOK}, {C.CS}, {C.LAB}, {C.NEAR} SELECT round(100 * avg(r), 6) AS balanced, round(100 * max(n) / sum(n), 6) AS majority FROM (SELECT label, avg(CAST(label = predicted AS INTEGER)) AS r, count(*) AS n FROM pred GROUP BY 1)")
def balanced_accuracy(spark, d):
    return C.rounded(A.balanced_accuracy(C._centroid(spark, d)), "balanced", "majority")


# Joins


@query(f"WITH {C.CUST}, {C.CS} SELECT c_custkey AS row_id, count(bucket) AS filled FROM customer LEFT JOIN cs ON c_custkey = row_id GROUP BY 1")
def left_join_empty_rows(spark, d):
    """Customers, those without orders too, and their filled cells."""
    cs = O.countsketch(M.custpart(spark, d), C.R, C.SEED)
    return M.table(spark, d, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "row_id").join(cs, "row_id", "left").groupBy("row_id").agg(F.count("bucket").alias("filled"))


@query("SELECT d.doc_id IS NOT NULL AS has_text, l.doc_id IS NOT NULL AS has_label, count(*) AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id + 3 GROUP BY 1, 2")
def full_join_labels(spark, d):
    x = M.table(spark, d, "documents", ["doc_id"]).withColumnRenamed("doc_id", "a")
    y = M.table(spark, d, "labels", ["doc_id"]).select((F.col("doc_id") + 3).alias("b"))
    return x.join(y, F.col("a") == F.col("b"), "full").groupBy(F.col("a").isNotNull().alias("has_text"), F.col("b").isNotNull().alias("has_label")).agg(F.count("*").alias("n"))


@query("SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def anti_join_unseen(spark, d):
    """Parts that no large line has, features that a map fitted on those lines never met."""
    seen = M.table(spark, d, "lineitem", ["l_partkey", "l_quantity"]).where("l_quantity > 45")
    parts = M.table(spark, d, "part", ["p_partkey"])
    return parts.join(seen, parts.p_partkey == seen.l_partkey, "left_anti")


@query("SELECT p_brand, lo, count(*) AS n FROM part JOIN range(900, 2200, 100) t(lo) ON p_retailprice >= lo AND p_retailprice < lo + 100 GROUP BY 1, 2")
def range_join_cells(spark, d):
    """Prices to cells, by the cell's number: an equi-join in place of a comparison of all pairs."""
    cells = spark.range(900, 2200, 100).select(F.col("id").alias("lo"), (F.col("id") / 100).cast("long").alias("cell"))
    part = M.table(spark, d, "part", ["p_brand", "p_retailprice"]).withColumn("cell", F.floor(F.col("p_retailprice") / 100))
    return part.join(F.broadcast(cells), "cell").groupBy("p_brand", "lo").agg(F.count("*").alias("n"))


@query("SELECT a.event_id, b.event_id AS seen_id FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def as_of_join(spark, d):
    """For each purchase the view in force: the last one of the user at that time or before, by one sort of each user's events."""
    e = M.table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"]).where("event_type in ('view', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("seen_id", seen).where("event_type = 'purchase'").select("event_id", "seen_id")


@query("SELECT o_custkey, l_partkey, l_quantity FROM (SELECT o_custkey, l_partkey, l_quantity, row_number() OVER (PARTITION BY o_orderkey ORDER BY l_quantity DESC, l_linenumber, l_partkey) AS k FROM orders JOIN lineitem ON o_orderkey = l_orderkey) WHERE k <= 2")
def top_lines_of_orders(spark, d):
    """The two largest lines of each order, as a ranked join."""
    o, li = M.table(spark, d, "orders", ["o_orderkey", "o_custkey"]), M.table(spark, d, "lineitem", ["l_orderkey", "l_partkey", "l_quantity", "l_linenumber"])
    w = Window.partitionBy("l_orderkey").orderBy(F.desc("l_quantity"), "l_linenumber", "l_partkey")
    return li.withColumn("k", F.row_number().over(w)).where("k <= 2").join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_partkey", "l_quantity")


@query("SELECT e.user_id, CAST(t.k AS INTEGER) AS k, count(*) AS n FROM events e, LATERAL (SELECT unnest([CAST(json_extract_string(e.props, '$.k') AS INTEGER), CAST(json_extract_string(e.props, '$.k') AS INTEGER) // 10]) AS k) t GROUP BY 1, 2")
def lateral_join_levels(spark, d):
    """Each event's feature and the feature's group, by a lateral table."""
    e = M.table(spark, d, "events", ["user_id", "props"])
    return spark.sql("SELECT user_id, t.k, count(*) AS n FROM (SELECT user_id, CAST(get_json_object(props, '$.k') AS INT) AS f FROM {e}), LATERAL (SELECT explode(array(f, f DIV 10)) AS k) t GROUP BY 1, 2", e=e).select("user_id", F.col("k").cast("int").alias("k"), "n")


# Aggregates


@query("SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS f, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM lineitem GROUP BY 1")
def pivot_flags(spark, d):
    out = M.table(spark, d, "lineitem", ["l_returnflag", "l_linestatus"]).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return out.select("l_returnflag", F.coalesce("F", F.lit(0)).cast("long").alias("f"), F.coalesce("O", F.lit(0)).cast("long").alias("o"))


@query("SELECT p_partkey, 'p_size' AS name, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def unpivot_part(spark, d):
    part = M.table(spark, d, "part", ["p_partkey", "p_size", "p_retailprice"]).withColumn("p_size", F.col("p_size").cast("double"))
    return part.unpivot("p_partkey", ["p_size", "p_retailprice"], "name", "value")


def _grouping(kind: str, sql_kind: str) -> str:
    return f"SELECT l_returnflag AS flag, l_linestatus AS status, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS INTEGER) AS level, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem GROUP BY {sql_kind}"


def _levels(spark, d, kind: str) -> DataFrame:
    li = M.table(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity"])
    return spark.sql(f"SELECT l_returnflag AS flag, l_linestatus AS status, CAST(grouping_id() AS INT) AS level, count(*) AS n, sum(l_quantity) AS quantity FROM {{li}} GROUP BY {kind}", li=li)


@query(_grouping("", "ROLLUP (l_returnflag, l_linestatus)"))
def rollup_flags(spark, d):
    return _levels(spark, d, "ROLLUP (l_returnflag, l_linestatus)")


@query(_grouping("", "CUBE (l_returnflag, l_linestatus)"))
def cube_flags(spark, d):
    return _levels(spark, d, "CUBE (l_returnflag, l_linestatus)")


@query(_grouping("", "GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())"))
def grouping_sets_flags(spark, d):
    return _levels(spark, d, "l_returnflag, l_linestatus GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())")


@query("SELECT count(DISTINCT token) AS tokens, true AS near FROM (SELECT unnest(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+')) AS token FROM documents) WHERE token <> ''")
def approximate_features(spark, d):
    """The number of features, exactly, and whether the sketch of it is within 6 percent."""
    t = M.table(spark, d, "documents", ["text"]).select(F.explode(F.split(F.lower("text"), M.SEPARATORS)).alias("token")).where("token != ''")
    one = t.agg(F.countDistinct("token").alias("tokens"), F.approx_count_distinct("token", 0.02).alias("about"))
    return one.select("tokens", (F.abs(F.col("about") - F.col("tokens")) <= 0.06 * F.col("tokens")).alias("near"))


@query(f"WITH {C.CUST}, {C.SIGNED}, {C.PICK}, {C.INIT} SELECT bucket, sum(abs(value)) AS l1 FROM c GROUP BY 1")
def l1_by_grouped_function(spark, d):
    """Norms of centres by a grouped aggregate function in Python, as a check of the built-in sums."""

    @F.pandas_udf("double")
    def l1_norm(v: pd.Series) -> float:
        return float(v.abs().sum())

    return K.init_centres(C._m(spark, d), C.R, C.SEED).groupBy("bucket").agg(l1_norm("value").alias("l1"))


@query(f"WITH {C.CUST}, {C.SIGNED}, {C.PICK}, {C.INIT} SELECT row_id, bucket, sign(value) * greatest(0, abs(value) - 10) AS value FROM c WHERE abs(value) > 10")
def soft_by_vector_function(spark, d):
    @F.pandas_udf("double")
    def soft(v: pd.Series) -> pd.Series:
        return v.where(v.abs() > 10, 0.0).map(lambda x: x - 10 if x > 0 else x + 10 if x < 0 else 0.0)

    return K.init_centres(C._m(spark, d), C.R, C.SEED).select("row_id", "bucket", soft("value").alias("value")).where("value != 0")


@query("SELECT p_brand, p_partkey, CAST(row_number() OVER w AS INTEGER) AS place, CAST(rank() OVER r AS INTEGER) AS rank_, CAST(dense_rank() OVER r AS INTEGER) AS dense, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(percent_rank() OVER r, 9) AS share, round(cume_dist() OVER r, 9) AS cume FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), r AS (PARTITION BY p_brand ORDER BY p_size)")
def ranking_windows(spark, d):
    w, r = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    part = M.table(spark, d, "part", ["p_brand", "p_partkey", "p_size"])
    return part.select("p_brand", "p_partkey", F.row_number().over(w).alias("place"), F.rank().over(r).alias("rank_"), F.dense_rank().over(r).alias("dense"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(r), 9).alias("share"), F.round(F.cume_dist().over(r), 9).alias("cume"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER f AS first_id, last_value(event_id) OVER f AS last_id, nth_value(event_id, 2) OVER f AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def analytic_windows(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    f = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = M.table(spark, d, "events", ["event_id", "user_id", "ts"])
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first("event_id").over(f).alias("first_id"), F.last("event_id").over(f).alias("last_id"), F.nth_value("event_id", 2).over(f).alias("second_id"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 12 HOUR PRECEDING AND CURRENT ROW) AS recent FROM events")
def moving_counts(spark, d):
    """Events of the user in the twelve hours up to each event."""
    e = M.table(spark, d, "events", ["event_id", "user_id", "ts"]).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-12 * 3600 * 1_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("recent"))


# Sets, subqueries, recursion

_TOKENS = "SELECT DISTINCT unnest(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+')) AS token FROM "


def _tokens(spark, d, name: str) -> DataFrame:
    return M.table(spark, d, name, ["text"]).select(F.explode(F.split(F.lower("text"), M.SEPARATORS)).alias("token")).distinct()


@query(f"({_TOKENS} documents) INTERSECT ({_TOKENS} benchmark)")
def common_vocabulary(spark, d):
    return _tokens(spark, d, "documents").intersect(_tokens(spark, d, "benchmark"))


@query(f"({_TOKENS} benchmark) EXCEPT ({_TOKENS} documents)")
def vocabulary_of_benchmark_alone(spark, d):
    return _tokens(spark, d, "benchmark").subtract(_tokens(spark, d, "documents"))


@query("SELECT o_orderpriority, count(*) AS n FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 40) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0) GROUP BY 1")
def nested_queries(spark, d):
    """A scalar, a correlated and an IN subquery."""
    names = {n: M.table(spark, d, n) for n in ("orders", "lineitem", "customer")}
    return spark.sql("SELECT o_orderpriority, count(*) AS n FROM {orders} o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders}) AND EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 40) AND o_custkey IN (SELECT c_custkey FROM {customer} WHERE c_acctbal > 0) GROUP BY 1", **names)


_BY_LINE = "SELECT sum(a) AS l1, max(a) AS top, array_agg(a) AS every FROM (SELECT l_linenumber, CAST(sum(l_quantity) AS DOUBLE) AS a FROM {lineitem} GROUP BY 1)"
_BISECT = "b(k, lo, hi, left_) AS (SELECT 0 AS k, CAST(0 AS DOUBLE) AS lo, top AS hi, l1 AS left_ FROM {t} UNION ALL SELECT k + 1, CASE WHEN l < l1 / 2 THEN lo ELSE mid END, CASE WHEN l < l1 / 2 THEN mid ELSE hi END, l FROM (SELECT k, lo, hi, left_, l1, (lo + hi) / 2 AS mid, {left} AS l FROM b CROSS JOIN {t} WHERE (left_ > l1 / 2 * 1.1 OR left_ < l1 / 2) AND k < 64)) SELECT CAST(k AS INTEGER) AS k, CAST(lo AS DOUBLE) AS lo, CAST(hi AS DOUBLE) AS hi, CAST(left_ AS DOUBLE) AS left_ FROM b"
_LEFT = "list_sum([greatest(x - (lo + hi) / 2, 0) FOR x IN every])"


@query(f"WITH RECURSIVE t AS ({_BY_LINE.format(lineitem='lineitem')}), {_BISECT.format(t='t', left=_LEFT)}")
def recursive_bisection(spark, d):
    """The intervals of the projection of the quantities by line number to half their L1 norm with tolerance 0.1, as a recursive query."""
    t = cut(spark.sql(_BY_LINE, lineitem=M.table(spark, d, "lineitem", ["l_linenumber", "l_quantity"])))  # one row, read by every halving
    left = "aggregate(every, CAST(0 AS DOUBLE), (s, x) -> s + greatest(x - (lo + hi) / 2, 0))"
    return spark.sql("WITH RECURSIVE " + _BISECT.replace("{left}", left), t=t)


@query(f"SELECT doc_id FROM documents WHERE {H.drawn_sql('doc_id', 0.25, 7, 'rows')}")
def hash_sample(spark, d):
    return M.table(spark, d, "documents", ["doc_id"]).where(H.drawn(F.col("doc_id"), 0.25, 7, "rows"))


# Functions


@query("SELECT user_id, event_type || ':' || lpad(CAST(hour(ts) AS VARCHAR), 2, '0') AS feature, count(*) AS n, CAST(datediff('day', min(CAST(ts AS DATE)), max(CAST(ts AS DATE))) AS INTEGER) AS days FROM events GROUP BY 1, 2")
def features_by_hour(spark, d):
    e = M.table(spark, d, "events", ["user_id", "event_type", "ts"])
    day = F.to_date("ts")
    return e.groupBy("user_id", F.concat_ws(":", "event_type", F.lpad(F.hour("ts").cast("string"), 2, "0")).alias("feature")).agg(F.count("*").alias("n"), F.datediff(F.max(day), F.min(day)).alias("days"))


@query("SELECT doc_id, count(*) AS words, sum(n) AS tokens, max(n) AS most FROM (SELECT doc_id, token, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+')) AS token FROM documents) WHERE token <> '' GROUP BY 1, 2) GROUP BY 1")
def token_maps(spark, d):
    """Counts of each text as a map, and figures from its entries."""
    t = M.table(spark, d, "documents", ["doc_id", "text"]).select("doc_id", F.explode(F.split(F.lower("text"), M.SEPARATORS)).alias("token")).where("token != ''")
    m = t.groupBy("doc_id", "token").agg(F.count("*").alias("n")).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("token", "n"))).alias("m"))
    v = F.map_values("m")
    return m.select("doc_id", F.cardinality("m").cast("long").alias("words"), F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + x).alias("tokens"), F.array_max(v).alias("most"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_features(spark, d):
    e = M.table(spark, d, "events", ["event_id", "props"])
    return e.select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT p_partkey, coalesce(nullif(p_size, 1), -1) AS size, CASE WHEN p_type IS NULL THEN 'none' ELSE lower(p_type) END AS kind FROM part")
def null_handling(spark, d):
    p = M.table(spark, d, "part", ["p_partkey", "p_size", "p_type"])
    return p.select("p_partkey", F.coalesce(F.nullif("p_size", F.lit(1)), F.lit(-1)).alias("size"), F.coalesce(F.lower("p_type"), F.lit("none")).alias("kind"))


@query(f"WITH {C.CUST} SELECT row_id, len(list(feature_id)) AS n, list_sum(list(value)) AS total FROM e GROUP BY 1")
def rows_layout(spark, d):
    """Rows as lists, and figures from the lists."""
    r = M.custpart(spark, d).as_rows()
    return r.select("row_id", F.size("idx").cast("long").alias("n"), F.aggregate("val", F.lit(0.0), lambda a, x: a + x).alias("total")).where("n > 0")


def queries() -> dict:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)
