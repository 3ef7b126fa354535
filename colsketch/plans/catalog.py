"""Queries over the given tables and, where SQL can express them, DuckDB SQL with the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import measures as A
from ..operators import adaptive as K
from ..operators import l1ball as P
from ..operators import oblivious as O
from ..session import ship
from ..sources import formats
from ..sources import matrix as M
from ..streaming import sketch_stream as S
from . import solve as V
from . import workloads as W

SEED, R = 42, 16
CUST = "e AS (SELECT o_custkey AS row_id, l_partkey AS feature_id, CAST(sum(l_quantity) AS DOUBLE) AS value FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2 HAVING sum(l_quantity) <> 0)"
SUPP = "e AS (SELECT l_suppkey AS row_id, l_partkey AS feature_id, CAST(count(*) AS DOUBLE) AS value FROM lineitem GROUP BY 1, 2)"
EMB = "e AS (SELECT vec_id AS row_id, CAST(k AS BIGINT) AS feature_id, CAST(embedding[k + 1] AS DOUBLE) AS value FROM embeddings, range(0, 64) t(k))"
TOK = "e AS (SELECT doc_id AS row_id, ('0x' || substr(md5(token), 1, 13))::BIGINT AS feature_id, CAST(count(*) AS DOUBLE) AS value FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[ \\t\\r\\n]+')) AS token FROM documents) WHERE token <> '' GROUP BY doc_id, token)"
B, G = H.bucket_of_sql("feature_id", R, SEED), H.sign_of_sql("feature_id", SEED)
CS = f"cs AS (SELECT row_id, bucket, sum(v) AS value FROM (SELECT row_id, {B} AS bucket, value * {G} AS v FROM e) GROUP BY 1, 2 HAVING sum(v) <> 0)"
MAP = f"fmap AS (SELECT DISTINCT feature_id, {B} AS bucket, {G} AS sign FROM e), sizes AS (SELECT bucket, count(*) AS size FROM fmap GROUP BY 1)"
SUMS = "sums AS (SELECT row_id, bucket, sum(value * sign) AS t FROM e JOIN fmap USING (feature_id) GROUP BY 1, 2)"
SIGNED = f"m AS (SELECT row_id, feature_id, value * {G} AS value FROM e)"
PICK = "pick AS (" + H.sample_features_sql("(SELECT DISTINCT feature_id FROM e)", R, SEED) + ")"
INIT = "c AS (SELECT row_id, bucket, value FROM m JOIN pick USING (feature_id))"
ASSIGN = f"""sq AS (SELECT b AS bucket, coalesce(sum(value * value), 0) AS s FROM range(0, {R}) t(b) LEFT JOIN c ON c.bucket = b GROUP BY 1),
cross_ AS (SELECT m.feature_id, c.bucket, sum(m.value * c.value) AS p FROM m JOIN c USING (row_id) GROUP BY 1, 2),
dist AS (SELECT f.feature_id, sq.bucket, sq.s - 2 * coalesce(p, 0) AS d FROM (SELECT DISTINCT feature_id FROM e) f CROSS JOIN sq LEFT JOIN cross_ x ON x.feature_id = f.feature_id AND x.bucket = sq.bucket),
a AS (SELECT feature_id, CAST(bucket AS INTEGER) AS bucket FROM (SELECT *, row_number() OVER (PARTITION BY feature_id ORDER BY d, bucket) AS k FROM dist) WHERE k = 1)"""
MEAN = "n AS (SELECT bucket, count(*) AS size FROM a GROUP BY 1), c1 AS (SELECT row_id, bucket, sum(value) / max(size) AS value FROM m JOIN a USING (feature_id) JOIN n USING (bucket) GROUP BY 1, 2 HAVING sum(value) <> 0)"
FOLD = "CAST(('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8))::BIGINT % 5 AS INTEGER)"

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


def rounded(df: DataFrame, *names: str, places: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), places) + 0.0 for c in names})


# Count-sketch


@query(f"WITH {CUST}, {CS} SELECT * FROM cs")
def cs_custpart_sum(spark, d):
    return O.countsketch(M.custpart(spark, d), R, SEED)


@query(f"WITH {CUST}, {CS}, {MAP} SELECT row_id, cs.bucket, value / size AS value FROM cs JOIN sizes ON cs.bucket = sizes.bucket")
def cs_custpart_mean(spark, d):
    return O.countsketch(M.custpart(spark, d), R, SEED, "mean")


@query(f"WITH {CUST}, {CS}, {MAP} SELECT row_id, cs.bucket, round(value / sqrt(size), 6) + 0.0 AS value FROM cs JOIN sizes ON cs.bucket = sizes.bucket")
def cs_custpart_ortho(spark, d):
    return rounded(O.countsketch(M.custpart(spark, d), R, SEED, "ortho"), "value")


@query(f"WITH {CUST}, {MAP} SELECT feature_id, bucket, sign FROM fmap")
def cs_feature_map(spark, d):
    return O.feature_map(M.custpart(spark, d).features(), R, SEED)


@query(f"WITH {SUPP}, {CS} SELECT * FROM cs")
def cs_suppart(spark, d):
    return O.countsketch(M.suppart(spark, d), R, SEED)


@query(f"WITH {EMB}, {CS} SELECT row_id, bucket, round(value, 6) + 0.0 AS value FROM cs")
def cs_embeddings(spark, d):
    return rounded(O.countsketch(M.embeddings(spark, d), R, SEED), "value")


@query(f"WITH {TOK}, {CS} SELECT * FROM cs")
def cs_documents_tokens(spark, d):
    return O.countsketch(M.from_tokens(M.table(spark, d, "documents", ["doc_id", "text"]), "doc_id", F.col("text")), R, SEED)


@query(f"WITH {CUST} SELECT row_id, {B} AS bucket, sum(value) AS value FROM e GROUP BY 1, 2")
def cs_unsigned(spark, d):
    return O.countsketch(M.custpart(spark, d), R, SEED, signs="identity")


@query()
def cs_fast_family(spark, d):
    return O.countsketch(M.custpart(spark, d), R, SEED, family="xxhash64")


# Dense projections


def _gauss(var: str) -> str:
    return f"WITH {EMB} SELECT row_id, CAST(b AS INTEGER) AS bucket, round(sum(value * {H.normal_of_sql(SEED, 'feature_id', 'b')}) / sqrt({var}), 6) + 0.0 AS value FROM e, range(0, 8) t(b) GROUP BY 1, 2"


@query(_gauss("64.0"))
def gaussian_embeddings_per_d(spark, d):
    return rounded(O.gaussian(M.embeddings(spark, d), 8, SEED, "per_d", 64), "value")


@query(_gauss("8.0"))
def gaussian_embeddings_per_r(spark, d):
    return rounded(O.gaussian(M.embeddings(spark, d), 8, SEED, "per_r", 64), "value")


def _ternary(cte: str, r: int, density: float, scale: float, places: int = 6) -> str:
    u = H.uniform_of_sql(SEED, "feature_id", "b")
    return f"WITH {cte} SELECT row_id, CAST(b AS INTEGER) AS bucket, round(sum(CASE WHEN u < {density / 2!r} THEN -value ELSE value END) * {scale!r}, {places}) + 0.0 AS value FROM (SELECT *, {u} AS u FROM e, range(0, {r}) t(b)) WHERE u < {density!r} GROUP BY 1, 2 HAVING sum(CASE WHEN u < {density / 2!r} THEN -value ELSE value END) <> 0"


@query(_ternary(EMB, 8, 1 / 3, 3**0.5))
def ternary_embeddings(spark, d):
    return rounded(O.ternary(M.embeddings(spark, d), 8, SEED), "value")


@query(_ternary(CUST, 8, 0.02, 1.0))
def ternary_sparse_custpart(spark, d):
    return rounded(O.ternary(M.custpart(spark, d), 8, SEED, 0.02, False), "value")


HAD = f"h AS (SELECT row_id, CAST(b AS INTEGER) AS bucket, sum(value * {G} * (1 - 2 * (bit_count(feature_id & b) % 2))) / 8.0 AS value FROM e, range(0, 64) t(b) GROUP BY 1, 2)"
COORD = "pick AS (" + H.sample_features_sql("(SELECT k AS feature_id FROM range(0, 64) t(k))", 8, SEED, "coordinates") + ")"


@query(f"WITH {EMB}, {HAD} SELECT row_id, bucket, round(value, 6) + 0.0 AS value FROM h WHERE value <> 0")
def hadamard_embeddings(spark, d):
    return rounded(O.hadamard_rotate(M.embeddings(spark, d), 64, SEED), "value")


@query(f"WITH {EMB}, {HAD}, {COORD} SELECT row_id, pick.bucket, round(value * sqrt(8.0), 6) + 0.0 AS value FROM h JOIN pick ON h.bucket = pick.feature_id")
def hadamard_subsample(spark, d):
    return rounded(O.hadamard(M.embeddings(spark, d), 64, 8, SEED), "value")


@query(f"WITH {EMB}, {HAD}, {COORD} SELECT row_id, pick.bucket, round(value * sqrt(8.0), 6) + 0.0 AS value FROM h JOIN pick ON h.bucket = pick.feature_id")
def hadamard_pruned(spark, d):
    return rounded(O.hadamard_pruned(M.embeddings(spark, d), 64, 8, SEED), "value")


@query(f"WITH {EMB}, {HAD} SELECT bucket, round(sum(value * value), 6) AS score FROM h GROUP BY 1")
def hadamard_topr_scores(spark, d):
    return rounded(O.hadamard_scores(M.embeddings(spark, d), 64, SEED), "score")


@query(f"WITH {EMB}, {HAD}, top AS (SELECT bucket AS b0, CAST(row_number() OVER (ORDER BY s DESC, bucket) - 1 AS INTEGER) AS b FROM (SELECT bucket, sum(value * value) AS s FROM h GROUP BY 1) ORDER BY s DESC, bucket LIMIT 8) SELECT row_id, b AS bucket, round(value, 6) + 0.0 AS value FROM h JOIN top ON bucket = b0")
def hadamard_topr_embeddings(spark, d):
    return rounded(O.hadamard_topr(M.embeddings(spark, d), 64, 8, SEED), "value")


@query(f"WITH {EMB}, f AS (SELECT DISTINCT feature_id FROM e WHERE value <> 0) SELECT CAST(i.feature_id AS INTEGER) AS i, CAST(j.feature_id AS INTEGER) AS j, CAST(1 - 2 * (bit_count(i.feature_id & j.feature_id) % 2) AS INTEGER) AS h FROM f i, f j")
def hadamard_matrix(spark, d):
    """The transform's entries for the features that occur in the embeddings."""
    return O.hadamard_entries(M.embeddings(spark, d).features())


@query()
def orthonormal_embeddings(spark, d):
    return O.orthonormal(M.embeddings(spark, d), 64, 8, SEED)


@query()
def pca_embeddings(spark, d):
    return O.pca(M.embeddings(spark, d), 64, 8)


@query()
def approx_svd_embeddings(spark, d):
    return O.approx_svd(M.embeddings(spark, d), 8, SEED)


@query()
def hadamard_energy_sampled(spark, d):
    return O.hadamard_topr(M.embeddings(spark, d), 64, 8, SEED, "sample")


@query(f"WITH {EMB}, s AS (SELECT feature_id, min(value) AS lo, max(value) AS hi FROM e GROUP BY 1) SELECT row_id, feature_id, round(2 * (value - lo) / (hi - lo) - 1, 6) + 0.0 AS value FROM e JOIN s USING (feature_id) WHERE hi > lo AND 2 * (value - lo) / (hi - lo) - 1 <> 0")
def minmax_embeddings(spark, d):
    return rounded(M.min_max(M.embeddings(spark, d)).entries, "value")


# Learned sketch


def _m(spark, d):
    return K.signed(M.custpart(spark, d), SEED)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT} SELECT * FROM c")
def init_columns(spark, d):
    return K.init_centres(_m(spark, d), R, SEED)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT} SELECT m.feature_id, c.bucket, sum(m.value * c.value) AS product FROM m JOIN c USING (row_id) GROUP BY 1, 2")
def cross_products(spark, d):
    m = _m(spark, d)
    return K.cross_products(m, K.init_centres(m, R, SEED))


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN} SELECT * FROM a")
def assign_once(spark, d):
    m = _m(spark, d)
    return K.assign(m, K.init_centres(m, R, SEED), R)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT} SELECT bucket, sum(abs(value)) AS l1, max(abs(value)) AS linf, sum(value * value) AS sq FROM c GROUP BY 1")
def centre_stats(spark, d):
    return P.stats(K.init_centres(_m(spark, d), R, SEED))


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT row_id, bucket, -2 * (sum(t) - max(size) * sum(c)) + 0.0 AS value FROM (SELECT row_id, bucket, sum(value) AS t, 0 AS c FROM m JOIN a USING (feature_id) GROUP BY 1, 2 UNION ALL SELECT row_id, bucket, 0, value FROM c) JOIN n USING (bucket) GROUP BY 1, 2")
def gradient_once(spark, d):
    m = _m(spark, d)
    c = K.init_centres(m, R, SEED)
    return K.gradient(m, K.assign(m, c, R), c).withColumn("value", F.col("value") + 0.0)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT * FROM c1 UNION ALL SELECT * FROM c WHERE bucket NOT IN (SELECT bucket FROM n)")
def step_per_centre(spark, d):
    m = _m(spark, d)
    c = K.init_centres(m, R, SEED)
    return K.step(m, K.assign(m, c, R), c)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT row_id, bucket, round(value, 6) + 0.0 AS value FROM (SELECT row_id, bucket, sum(c) * (1 - 2e-4 * max(size)) + 2e-4 * sum(t) AS value FROM (SELECT row_id, bucket, sum(value) AS t, 0 AS c FROM m JOIN a USING (feature_id) GROUP BY 1, 2 UNION ALL SELECT row_id, bucket, 0, value FROM c) JOIN n USING (bucket) GROUP BY 1, 2) WHERE round(value, 6) <> 0")
def step_constant(spark, d):
    m = _m(spark, d)
    c = K.init_centres(m, R, SEED)
    return rounded(K.step(m, K.assign(m, c, R), c, ("constant", 1e-4)), "value").where("value != 0")


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT row_id, bucket, value FROM c1")
def lloyd_step(spark, d):
    m = _m(spark, d)
    return K.means(m, K.assign(m, K.init_centres(m, R, SEED), R))


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT row_id, bucket, value FROM c1 UNION ALL SELECT * FROM c WHERE bucket NOT IN (SELECT bucket FROM n)")
def full_one_iteration(spark, d):
    return K.learn_full(M.custpart(spark, d), R, 1, seed=SEED).training_sketch()


THETA = "theta AS (SELECT bucket, max(th) AS theta FROM (SELECT bucket, (cum - 500) / k AS th, a, row_number() OVER (PARTITION BY bucket ORDER BY k DESC) AS last FROM (SELECT bucket, abs(value) AS a, sum(abs(value)) OVER (PARTITION BY bucket ORDER BY abs(value) DESC, row_id ROWS UNBOUNDED PRECEDING) AS cum, row_number() OVER (PARTITION BY bucket ORDER BY abs(value) DESC, row_id) AS k FROM c) WHERE a > (cum - 500) / k) WHERE last = 1 GROUP BY 1)"


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {THETA} SELECT bucket, round(greatest(theta, 0), 6) + 0.0 AS theta FROM theta")
def l1_exact_theta(spark, d):
    return rounded(P.exact_thresholds(K.init_centres(_m(spark, d), R, SEED), 500.0), "theta")


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {THETA} SELECT row_id, bucket, round(sign(value) * greatest(0, abs(value) - greatest(theta, 0)), 6) + 0.0 AS value FROM c JOIN theta USING (bucket) WHERE abs(value) > greatest(theta, 0)")
def soft_threshold(spark, d):
    return rounded(P.project(K.init_centres(_m(spark, d), R, SEED), 500.0, 0), "value")


@query(f"""WITH RECURSIVE {CUST}, {SIGNED}, {PICK}, {INIT}, st AS (SELECT bucket, sum(abs(value)) AS l1, max(abs(value)) AS top FROM c GROUP BY 1),
b AS (SELECT bucket, l1, top, CAST(0 AS INTEGER) AS k, CAST(0 AS DOUBLE) AS lo, CAST(top AS DOUBLE) AS hi, CASE WHEN l1 <= 550 THEN 0.0::DOUBLE ELSE NULL END AS theta FROM st
UNION ALL SELECT bucket, l1, top, k + 1, CASE WHEN l > 550 THEN (lo + hi) / 2 ELSE lo END, CASE WHEN l < 500 THEN (lo + hi) / 2 ELSE hi END, CASE WHEN l BETWEEN 500 AND 550 THEN (lo + hi) / 2 ELSE NULL END
FROM (SELECT b.*, (SELECT sum(greatest(0, abs(value) - (b.lo + b.hi) / 2)) FROM c WHERE c.bucket = b.bucket) AS l FROM b WHERE theta IS NULL AND k < 64))
SELECT bucket, round(theta, 6) + 0.0 AS theta FROM b WHERE theta IS NOT NULL""")
def l1_bisect_theta(spark, d):
    return rounded(P.thresholds(K.init_centres(_m(spark, d), R, SEED), 500.0, 0.1).select("bucket", "theta"), "theta")


BATCH = "pick AS (" + H.sample_features_sql("(SELECT DISTINCT feature_id FROM e)", 200, SEED, "/batch1") + ")"


@query(f"WITH {CUST}, {BATCH} SELECT feature_id FROM pick")
def minibatch_sample(spark, d):
    return H.sample_features(M.custpart(spark, d).features(), 200, SEED, "/batch1").select("feature_id")


@query()
def learned_full_custpart(spark, d):
    return K.learn_full(M.custpart(spark, d), R, 3, 2000.0, 0.1, SEED).training_sketch()


@query()
def learned_minibatch_custpart(spark, d):
    return K.learn_minibatch(M.custpart(spark, d), R, 3, 0.2, 2000.0, 0.1, SEED).training_sketch()


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, {MEAN} SELECT row_id, bucket, value FROM c1")
def transform_none(spark, d):
    fm = M.custpart(spark, d)
    return K.learn_full(fm, R, 1, seed=SEED).transform(fm, "none")


@query()
def transform_theta(spark, d):
    fm = M.custpart(spark, d)
    return K.learn_full(fm, R, 2, 2000.0, seed=SEED).transform(fm, "theta")


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN} SELECT feature_id, bucket FROM a")
def final_assignment(spark, d):
    return K.learn_full(M.custpart(spark, d), R, 1, seed=SEED).feature_map.select("feature_id", "bucket")


# Measures


def _cust_map(spark, d):
    fm = M.custpart(spark, d)
    return fm, O.feature_map(fm.features(), R, SEED)


ERR = "(SELECT sum(value * value) FROM e) - (SELECT sum(t * t / size) FROM sums JOIN sizes USING (bucket))"


@query(f"WITH {CUST}, {MAP}, {SUMS} SELECT round({ERR}, 2) AS error, round(({ERR}) / (SELECT sum(value * value) FROM e), 9) AS relative")
def reconstruction_error(spark, d):
    df = A.reconstruction_error(*_cust_map(spark, d))
    return df.select(F.round("error", 2).alias("error"), F.round("relative", 9).alias("relative"))


@query(f"WITH {CUST}, {MAP}, {SUMS} SELECT round({ERR}, 2) AS objective")
def kmeans_objective(spark, d):
    fm, fmap = _cust_map(spark, d)
    return A.kmeans_objective(fm, fmap, O.countsketch(fm, R, SEED, "mean")).select(F.round("objective", 2).alias("objective"))


@query("SELECT true AS equal")
def identity_gap(spark, d):
    fm, fmap = _cust_map(spark, d)
    a = A.reconstruction_error(fm, fmap).crossJoin(A.kmeans_objective(fm, fmap, O.countsketch(fm, R, SEED, "mean")))
    return a.select((F.abs(F.col("error") - F.col("objective")) < 1e-9 * F.col("error")).alias("equal"))


@query(f"WITH {CUST}, {CS} SELECT (SELECT count(DISTINCT row_id) FROM e) AS n, (SELECT count(*) FROM cs) AS filled, 1 - (SELECT count(*) FROM cs) / ((SELECT count(DISTINCT row_id) FROM e) * {R}) AS zeros")
def sparsity_countsketch(spark, d):
    fm = M.custpart(spark, d)
    return A.sparsity(O.countsketch(fm, R, SEED), fm.rows, R)


@query(f"WITH {CUST}, {MAP} SELECT {R} - count(*) AS empty_groups, max(size) AS largest, CAST(sum(size) AS BIGINT) AS features FROM sizes")
def group_profile(spark, d):
    return A.group_profile(_cust_map(spark, d)[1], R)


@query(f"WITH {CUST}, {MAP} SELECT bucket, size, size * (1 / size) AS gram FROM sizes")
def orthonormality(spark, d):
    return A.orthonormality(_cust_map(spark, d)[1])


def _profile(cte: str, name: str, rows: str) -> str:
    return f"SELECT '{name}' AS dataset, ({rows}) AS n, count(DISTINCT feature_id) AS d, count(*) AS nnz, round(1 - count(*) / (({rows}) * count(DISTINCT feature_id)), 9) AS zeros FROM (WITH {cte} SELECT * FROM e)"


@query(" UNION ALL ".join([_profile(CUST, "custpart", "SELECT count(DISTINCT o_custkey) FROM orders JOIN lineitem ON o_orderkey = l_orderkey"), _profile(SUPP, "suppart", "SELECT count(DISTINCT l_suppkey) FROM lineitem"), _profile(EMB, "embeddings", "SELECT count(*) FROM embeddings"), _profile(TOK, "documents", "SELECT count(*) FROM documents")]))
def profile_all(spark, d):
    docs = M.from_tokens(M.table(spark, d, "documents", ["doc_id", "text"]), "doc_id", F.col("text"))
    sets = {"custpart": M.custpart(spark, d), "suppart": M.suppart(spark, d), "embeddings": M.embeddings(spark, d), "documents": docs}
    out = None
    for name, fm in sets.items():
        one = A.profile(fm).select(F.lit(name).alias("dataset"), "n", "d", "nnz", F.round("zeros", 9).alias("zeros"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"WITH {CUST}, {CS} SELECT row_id, count(*) AS projection, coalesce((SELECT count(*) FROM cs WHERE cs.row_id = e.row_id), 0) AS classification FROM e GROUP BY row_id")
def prediction_ops(spark, d):
    fm = M.custpart(spark, d)
    return A.prediction_ops(fm, O.countsketch(fm, R, SEED), "countsketch", R, 0)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT} SELECT CAST(sum(x.n * y.n) AS BIGINT) AS products FROM (SELECT row_id, count(*) AS n FROM m GROUP BY 1) x JOIN (SELECT row_id, count(*) AS n FROM c GROUP BY 1) y USING (row_id)")
def embed_ops(spark, d):
    m = _m(spark, d)
    return A.embed_ops(m, K.init_centres(m, R, SEED))


NEXT = "p AS (SELECT vec_id AS i, vec_id + k AS j FROM embeddings CROSS JOIN range(1, 8) t(k))"


@query(f"WITH {EMB}, {CS}, {NEXT}, t AS (SELECT i, j, sum((a.value - b.value) * (a.value - b.value)) AS t FROM p JOIN e a ON a.row_id = i JOIN e b ON b.row_id = j AND a.feature_id = b.feature_id GROUP BY 1, 2), g AS (SELECT i, j, sum(d * d) AS g FROM (SELECT i, j, bucket, sum(s * value) AS d FROM (SELECT i, j, i AS row_id, 1 AS s FROM p UNION ALL SELECT i, j, j, -1 FROM p) JOIN cs USING (row_id) GROUP BY 1, 2, 3) GROUP BY 1, 2) SELECT count(*) AS pairs, round(avg(coalesce(g, 0) / t), 6) AS mean_ratio, avg(CASE WHEN coalesce(g, 0) / t BETWEEN 0.5 AND 1.5 THEN 1.0::DOUBLE ELSE 0 END) AS share FROM t LEFT JOIN g USING (i, j) WHERE t > 0")
def distortion_pairs(spark, d):
    """Each row with the next seven ids."""
    fm = M.embeddings(spark, d)
    rows = fm.rows.distinct()
    pairs = rows.select(F.col("row_id").alias("i"), F.explode(F.sequence(F.col("row_id") + 1, F.col("row_id") + 7)).alias("j"))
    pairs = pairs.join(rows.withColumnRenamed("row_id", "j"), "j", "left_semi").select("i", "j")
    return rounded(A.distortion(fm, O.countsketch(fm, R, SEED), pairs, 0.5), "mean_ratio")


@query()
def l1_feasible(spark, d):
    return A.l1_feasible(P.project(K.init_centres(_m(spark, d), R, SEED), 500.0, 0.1), 500.0, 0.1)


LAB = f"rows_ AS (SELECT doc_id AS row_id, CAST(lang = 'en' AS INTEGER) AS label, {FOLD} AS fold FROM documents)"
NEAR = "per AS (SELECT fold, label, bucket, sum(value) AS s FROM rows_ JOIN cs USING (row_id) GROUP BY 1, 2, 3), mean_ AS (SELECT t.test, p.label AS guess, bucket, sum(s) / max(n) AS c FROM per p JOIN (SELECT DISTINCT fold AS test FROM rows_) t ON p.fold <> t.test JOIN (SELECT a.test, label, count(*) AS n FROM rows_ r JOIN (SELECT DISTINCT fold AS test FROM rows_) a ON r.fold <> a.test GROUP BY 1, 2) z ON z.test = t.test AND z.label = p.label GROUP BY 1, 2, 3), norm_ AS (SELECT test, guess, sum(c * c) AS sq FROM mean_ GROUP BY 1, 2), dots AS (SELECT r.row_id, guess, sum(value * c) AS dot FROM rows_ r JOIN cs USING (row_id) JOIN mean_ m ON m.test = r.fold AND m.bucket = cs.bucket GROUP BY 1, 2), pred AS (SELECT row_id, fold, label, arg_min(guess, struct_pack(d := round(sq - 2 * coalesce(dot, 0), 9), g := guess)) AS predicted FROM rows_ r JOIN norm_ n ON n.test = r.fold LEFT JOIN dots USING (row_id, guess) GROUP BY 1, 2, 3)"


def _centroid(spark, d):
    docs = M.table(spark, d, "documents", ["doc_id", "text", "lang"])
    sketch = O.countsketch(M.from_tokens(docs, "doc_id", F.col("text")), R, SEED)
    rows = V.folds(docs.select(F.col("doc_id").alias("row_id"), (F.col("lang") == "en").cast("int").alias("label")))
    return V.nearest_centroid(sketch, rows)


@query(f"WITH {TOK}, {CS}, {LAB}, {NEAR} SELECT label, predicted, count(*) AS n FROM pred GROUP BY 1, 2")
def confusion_nearest_centroid(spark, d):
    return A.confusion(_centroid(spark, d))


@query(f"WITH {TOK}, {CS}, {LAB}, {NEAR} SELECT fold, round(avg(CAST(label = predicted AS INTEGER)), 9) AS accuracy FROM pred GROUP BY 1")
def accuracy_by_fold(spark, d):
    return _centroid(spark, d).groupBy("fold").agg(F.round(F.avg((F.col("label") == F.col("predicted")).cast("double")), 9).alias("accuracy"))


@query(f"WITH {CUST}, {CS} SELECT a.bucket AS i, b.bucket AS j, sum(a.value * b.value) AS v FROM cs a JOIN cs b USING (row_id) GROUP BY 1, 2 UNION ALL SELECT bucket, -1, sum(value * (row_id % 7)) FROM cs GROUP BY 1")
def least_squares_gram(spark, d):
    fm = M.custpart(spark, d)
    return V.gram(O.countsketch(fm, R, SEED), fm.rows.select("row_id", F.pmod("row_id", F.lit(7)).cast("double").alias("y")))


# Streams


KSQL = "f AS (SELECT event_id, user_id, ts, CAST(json_extract_string(props, '$.k') AS BIGINT) AS feature_id FROM events), i AS (SELECT *, " + H.bucket_of_sql("feature_id", R, SEED) + " AS bucket, CAST(" + G + " AS BIGINT) AS delta FROM f WHERE feature_id IS NOT NULL AND user_id IS NOT NULL)"


def _increments(spark, d):
    schema = M.table(spark, d, "events").schema
    return S.increments(S.read_events(spark, f"{d}/events.parque[t]", schema), R, SEED)  # a pattern may name one file, a folder may not


@query(f"WITH {KSQL} SELECT user_id, bucket, CAST(sum(delta) AS BIGINT) AS value FROM i GROUP BY 1, 2")
def stream_running_sketch(spark, d):
    return S.drain(S.running_sketch(_increments(spark, d)))


@query(f"WITH {KSQL} SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS day, bucket, CAST(sum(delta) AS BIGINT) AS value FROM i GROUP BY 1, 2")
def stream_tumbling_sketch(spark, d):
    return S.drain(S.windowed_sketch(_increments(spark, d), "1 day")).select(F.unix_timestamp("w.start").alias("day"), "bucket", "value")


@query(f"WITH {KSQL} SELECT bucket, CAST(sum(delta) AS BIGINT) AS value, count(*) AS n FROM i GROUP BY 1")
def stream_deduplicated(spark, d):
    rows = S.drain(S.deduplicated(_increments(spark, d)), "append")
    return rows.groupBy("bucket").agg(F.sum("delta").alias("value"), F.count("*").alias("n"))


@query(f"WITH {KSQL} SELECT user_id, bucket, CAST(sum(delta) AS BIGINT) AS value FROM i GROUP BY 1, 2")
def stream_merge_of_sites(spark, d):
    rows = S.increments(M.table(spark, d, "events"), R, SEED)
    halves = [S.running_sketch(rows.where(F.pmod("event_id", F.lit(2)) == k)) for k in (0, 1)]
    return S.merged(*halves)


@query(f"WITH {KSQL} SELECT CAST(epoch(w) AS BIGINT) AS start, bucket, CAST(sum(delta) AS BIGINT) AS value FROM (SELECT *, unnest([to_timestamp(21600 * (floor(epoch(ts) / 21600) - k)) FOR k IN range(0, 4)]) AS w FROM i) GROUP BY 1, 2")
def stream_sliding_sketch(spark, d):
    return S.drain(S.windowed_sketch(_increments(spark, d), "1 day", "6 hours")).select(F.unix_timestamp("w.start").alias("start"), "bucket", "value")


@query(f"WITH {KSQL}, g AS (SELECT *, CASE WHEN epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 21600 THEN 0 ELSE 1 END AS fresh FROM i), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, CAST(sum(delta) AS BIGINT) AS value FROM s GROUP BY user_id, n")
def stream_session_sketch(spark, d):
    return S.drain(S.session_sketch(_increments(spark, d), "6 hours"), "complete").select("user_id", F.unix_timestamp("w.start").alias("start"), "value")


@query("SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_followed_by(spark, d):
    schema = M.table(spark, d, "events").schema
    of = lambda kind: S.read_events(spark, f"{d}/events.parque[t]", schema).where(F.col("event_type") == kind)
    return S.drain(S.followed_by(of("view"), of("purchase")), "append")


@query(f"WITH {KSQL} SELECT user_id, bucket, count(*) AS seen, round(avg(delta), 9) + 0.0 AS centre FROM i GROUP BY 1, 2")
def stream_online_centres(spark, d):
    cells = S.online_centres(_increments(spark, d).withColumnRenamed("delta", "value"))
    return rounded(S.drain(cells, "update"), "centre", places=9)


# Forms of matrices


@query(f"WITH {TOK} SELECT row_id, CAST(dense_rank() OVER (ORDER BY feature_id) - 1 AS BIGINT) AS feature_id, value FROM e")
def dense_ids_documents(spark, d):
    return M.dense_ids(M.from_tokens(M.table(spark, d, "documents", ["doc_id", "text"]), "doc_id", F.col("text")))[0].entries


@query(f"WITH {EMB}, s AS (SELECT * FROM e WHERE value <> 0) SELECT * FROM s UNION ALL SELECT a.row_id, 64 + a.feature_id * 64 + b.feature_id, a.value * b.value FROM s a JOIN s b ON a.row_id = b.row_id AND a.feature_id <= b.feature_id")
def quadratic_embeddings(spark, d):
    """All 64 dimensions: 2,144 features a row without zeros."""
    return M.quadratic(M.embeddings(spark, d), 64).entries


ID = "('0x' || substr(md5({}), 1, 13))::BIGINT"


@query(f"SELECT p_partkey AS row_id, {ID.format(chr(39) + 'p_size' + chr(39))} AS feature_id, CAST(p_size AS DOUBLE) AS value FROM part WHERE p_size <> 0 UNION ALL SELECT p_partkey, {ID.format(chr(39) + 'p_brand=' + chr(39) + ' || p_brand')}, 1.0::DOUBLE FROM part WHERE p_brand IS NOT NULL")
def columns_part(spark, d):
    return M.from_columns(M.table(spark, d, "part"), "p_partkey", ["p_size"], ["p_brand"]).entries


@query("SELECT page_id, trim(regexp_replace(regexp_replace(html, '(?is)<(?:script\\b.*?</script\\s*|style\\b.*?</style\\s*)>|<!--.*?-->|<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g')) AS text FROM pages")
def strip_tags_pages(spark, d):
    return M.table(spark, d, "pages", ["page_id", "html"]).select("page_id", formats.strip_tags(F.col("html")).alias("text"))


# Variants of the learned sketch


@query(f"WITH {CUST} SELECT round(0.2 * sum(abs(value)) / count(DISTINCT feature_id), 6) AS lam FROM e")
def relative_ball(spark, d):
    m = _m(spark, d)
    return m.agg(F.round(F.lit(0.2) * F.sum(F.abs("value")) / F.countDistinct("feature_id"), 6).alias("lam"))


@query(f"WITH {CUST}, {SIGNED} SELECT CAST({H.bucket_of_sql('row_id', 256, SEED + 1)} AS BIGINT) AS row_id, feature_id, sum(value * {H.sign_of_sql('row_id', SEED + 1)}) AS value FROM m GROUP BY 1, 2 HAVING sum(value * {H.sign_of_sql('row_id', SEED + 1)}) <> 0")
def row_sketch_custpart(spark, d):
    return K.row_sketched(_m(spark, d), "feature_id", 256, SEED)


@query(f"WITH {CUST}, {SIGNED}, {PICK}, {INIT}, {ASSIGN}, flips AS (SELECT feature_id, sq.bucket, sq.s - 2 * abs(coalesce(p, 0)) AS d, CASE WHEN p < 0 THEN -1 ELSE 1 END AS flip FROM (SELECT DISTINCT feature_id FROM e) f CROSS JOIN sq LEFT JOIN cross_ x USING (feature_id, bucket)) SELECT feature_id, CAST(bucket AS INTEGER) AS bucket, CAST(flip AS INTEGER) AS flip FROM (SELECT *, row_number() OVER (PARTITION BY feature_id ORDER BY d, bucket) AS k FROM flips) WHERE k = 1")
def assign_free_signs(spark, d):
    m = _m(spark, d)
    return K.free_signs(m, K.init_centres(m, R, SEED), R)


# Experiments


@query(f"WITH {CUST}, {CS} SELECT 'countsketch' AS method, (SELECT count(*) FROM e) AS projection, (SELECT count(*) FROM cs) AS classification UNION ALL SELECT 'gaussian', (SELECT count(DISTINCT row_id) FROM e) * (SELECT count(DISTINCT feature_id) FROM e) * {R}, (SELECT count(DISTINCT row_id) FROM e) * {R}")
def prediction_cost(spark, d):
    fm = M.custpart(spark, d)
    sketch = O.countsketch(fm, R, SEED)
    return W.prediction_cost(fm, {"countsketch": sketch, "gaussian": sketch}, R, fm.features().count())


#: Widths by data set, as in the published table of accuracies.
WIDTHS = {"emb10": 30, "bigram": 100, "embquad": 256, "bow_quality": 256, "bow_en": 256, "bow_multi": 256}
PANELS = ("bigram", "bow_quality", "bow_en", "bow_multi")
CS_GRID = tuple(10.0**k for k in range(-5, 6))
LAMS = (10.0, 20.0, 30.0, 40.0)
BALLS = [*LAMS, *(("relative", f) for f in (1.0, 0.5, 0.2, 0.1, 0.05))]


def _experiment(name: str, dataset: str, run) -> None:
    """Registers an experiment on one data set; the bare name is the one on bigrams. All use five folds."""
    f = lambda spark, d: run(spark, d, dataset)
    f.__name__ = name if dataset == "bigram" else f"{name}_{dataset}"
    query()(f)


for _set, _r in WIDTHS.items():
    _experiment("workload_methods", _set, lambda s, d, x, r=_r: W.methods(s, d, x, r))
    _experiment("workload_embedding_time", _set, lambda s, d, x, r=_r: W.embedding_time(s, d, x, r))
    _experiment("workload_stability", _set, lambda s, d, x: W.stability(s, d, x, 16))
    _experiment("workload_tuning", _set, lambda s, d, x, r=_r: W.tuning(s, d, x, r, CS_GRID, LAMS))
    _experiment("workload_ablations", _set, lambda s, d, x: W.ablations(s, d, x, 16))
for _set in PANELS:
    _experiment("workload_widths", _set, lambda s, d, x: W.compare(s, d, x, [4, 8, 16, 32, 64, 128, 256]))
    _experiment("workload_accuracy_by_zeros", _set, lambda s, d, x: W.compare(s, d, x, [16], ["countsketch", "learned_full"], lams=BALLS))


@query()
def low_rank_embeddings(spark, d):
    error, energy = V.low_rank(M.embeddings(spark, d), 8, SEED)
    return spark.createDataFrame([(8, error, energy)], "k int, error double, energy double")


def queries() -> dict:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)
