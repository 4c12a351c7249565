"""Kernels, maps, prox operators, projections, closed forms, the solver's path and the cost models, each with its SQL."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kernelblocks.functions import kernels, prox
from kernelblocks.functions.featuremaps import FourierMap, identity_map
from kernelblocks.functions.rng import portable_integer_sql, portable_normal_sql, portable_uniform_sql
from kernelblocks.operators import prep
from kernelblocks.plans import blockplan
from kernelblocks.queries.registry import query
from kernelblocks.queries.relational import r6
from kernelblocks.sources.tables import table

SIGMA, LAM = 1.0, 1e-3


def _vectors(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("x"))


_GRAM_SQL = (
    "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) "
    "SELECT a.vec_id AS i, b.vec_id AS j, round(exp(-(list_distance(a.e, b.e) ** 2) / 2), 6) AS k FROM v a JOIN v b ON a.vec_id <= b.vec_id"
)


@query(_GRAM_SQL)
def gaussian_gram(spark: SparkSession, d: str) -> DataFrame:
    return kernels.gram(_vectors(spark, d), kernels.make("gaussian", sigma=SIGMA)).select("i", "j", r6("k").alias("k"))


@query(
    f"WITH g AS ({_GRAM_SQL}), b AS (SELECT i, j, k FROM g WHERE i <> j UNION ALL SELECT j, i, k FROM g WHERE i <> j) "
    "SELECT i, j, k, place::INT AS place FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY k DESC, j) AS place FROM b) WHERE place <= 3"
)
def kernel_topk(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    near = kernels.nearest(_vectors(spark, d), kernels.make("gaussian", sigma=SIGMA), 3).select("i", "j", r6("k").alias("k"))
    w = Window.partitionBy("i").orderBy(F.desc("k"), "j")
    return near.withColumn("place", F.row_number().over(w)).where("place <= 3")


@query(
    "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e, CASE WHEN vec_id % 2 = 0 THEN 0.5::DOUBLE ELSE -0.25::DOUBLE END AS alpha FROM embeddings) "
    "SELECT b.vec_id, round(sum(a.alpha * exp(-(list_distance(a.e, b.e) ** 2) / 2)), 6) + 0.0 AS score FROM v a JOIN v b ON true GROUP BY b.vec_id"
)
def dual_prediction(spark: SparkSession, d: str) -> DataFrame:
    scored = kernels.weighted_sums(_vectors(spark, d), kernels.make("gaussian", sigma=SIGMA), lambda ids: np.where(ids % 2 == 0, 0.5, -0.25))
    return scored.select(F.col("row_id").alias("vec_id"), r6("score").alias("score"))


@query(
    f"WITH g AS (SELECT c_custkey AS r, q FROM customer, range(4) b(q)) SELECT r, q, {portable_integer_sql(7, 'r', 'q', 'duckdb')} AS h, round({portable_normal_sql(7, 'r', 'q', 'duckdb')}, 6) + 0.0 AS z FROM g"
)
def portable_normals(spark: SparkSession, d: str) -> DataFrame:
    """Four numbers for each customer, from its key."""
    g = table(spark, d, "customer").select(F.col("c_custkey").alias("r"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(3).cast("long"))).alias("q"))
    return g.select("r", "q", F.expr(portable_integer_sql(7, "r", "q")).alias("h"), r6(F.expr(portable_normal_sql(7, "r", "q"))).alias("z"))


_S = 8
_WAVES = (
    f"w AS (SELECT r, q, {portable_normal_sql(5, 'r', 'q', 'duckdb')} AS w FROM range(64) a(r), range({_S}) b(q)), "
    f"p AS (SELECT q, {math.pi!r}::DOUBLE * {portable_uniform_sql(5, '64', '2 * q', 'duckdb')} AS b FROM range({_S}) t(q)), "
    f"z AS (SELECT vec_id, label, w.q AS q, sqrt(2.0::DOUBLE / {_S}) * cos(sum(embedding[r + 1]::DOUBLE * w) + any_value(b)) AS z FROM embeddings, w JOIN p ON p.q = w.q GROUP BY vec_id, label, w.q)"
)


def _map() -> FourierMap:
    return FourierMap(64, _S, 2, 5, sigma=SIGMA, generator="portable")


@query(f"WITH {_WAVES} SELECT vec_id, q::INT AS feature, round(z, 6) + 0.0 AS z FROM z")
def rff_features(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.baselines.linear import materialize

    z = materialize(_vectors(spark, d).withColumn("y", F.array(F.lit(0.0))), _map())
    return z.select(F.col("row_id").alias("vec_id"), F.posexplode("z").alias("feature", "z")).select("vec_id", "feature", r6("z").alias("z"))


@query(
    f"WITH {_WAVES}, g AS (SELECT vec_id, list(z ORDER BY q) AS z FROM z GROUP BY vec_id), v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings), "
    "d AS (SELECT abs(list_dot_product(g.z, h.z) - exp(-(list_distance(a.e, b.e) ** 2) / 2)) AS gap FROM g JOIN g h ON g.vec_id <= h.vec_id JOIN v a ON a.vec_id = g.vec_id JOIN v b ON b.vec_id = h.vec_id) "
    "SELECT count(*) AS pairs, round(max(gap), 6) AS max_gap, round(avg(gap), 6) AS mean_gap FROM d"
)
def kernel_error(spark: SparkSession, d: str) -> DataFrame:
    """Features and kernel of all pairs, block by block; counts, maxima and sums are what leaves a block."""
    by_block = kernels.gaps(_vectors(spark, d), kernels.make("gaussian", sigma=SIGMA), _map().features)
    pairs = F.sum("pairs")
    return by_block.agg(pairs.alias("pairs"), r6(F.max("most")).alias("max_gap"), r6(F.sum("total") / pairs).alias("mean_gap"))


_W = [0.3 * (k + 1) * (-1) ** k for k in range(_S)]


@query(
    f"WITH {_WAVES}, c AS (SELECT unnest(range({_S})) AS q, unnest({_W}::DOUBLE[]) AS w) SELECT vec_id, round(sum(z * w), 6) + 0.0 AS score, CASE WHEN sum(z * w) >= 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS pred FROM z JOIN c USING (q) GROUP BY vec_id"
)
def predict_scores_small(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.admm.engine import Model, predict

    w = np.array(_W)[:, None]
    scored = predict(_vectors(spark, d), Model(_map(), [w[:4], w[4:]]))
    return scored.select(F.col("row_id").alias("vec_id"), r6(F.element_at("scores", 1)).alias("score"), "pred")


_LI = "l_orderkey, l_linenumber, l_partkey, l_suppkey"
_V, _Y = "((l_quantity - 25) / 10)", "(CASE WHEN l_discount > 0.05 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END)"
_SOFT = "sign({0}) * greatest(abs({0}) - {1}, 0)"


def _prox(spark: SparkSession, d: str, f) -> DataFrame:
    v = (F.col("l_quantity") - 25) / 10
    y = F.when(F.col("l_discount") > 0.05, 1.0).otherwise(-1.0)
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", r6(f(v, y)).alias("p"))


@query(f"SELECT {_LI}, round(({_V} + 0.8 * {_Y}) / 1.8, 6) + 0.0 AS p FROM lineitem")
def prox_squared(spark: SparkSession, d: str) -> DataFrame:
    return _prox(spark, d, lambda v, y: prox.prox_squared_col(v, y, 0.4))


@query(f"SELECT {_LI}, round({_Y} + {_SOFT.format(f'({_V} - {_Y})', '0.4')}, 6) + 0.0 AS p FROM lineitem")
def prox_absolute(spark: SparkSession, d: str) -> DataFrame:
    return _prox(spark, d, lambda v, y: prox.prox_absolute_col(v, y, 0.4))


@query(f"SELECT {_LI}, round(CASE WHEN {_V} * {_Y} >= 1 THEN {_V} WHEN {_V} * {_Y} <= 0.6 THEN {_V} + 0.4 * {_Y} ELSE {_Y} END, 6) + 0.0 AS p FROM lineitem")
def prox_hinge(spark: SparkSession, d: str) -> DataFrame:
    return _prox(spark, d, lambda v, y: prox.prox_hinge_col(v, y, 0.4))


@query(f"SELECT {_LI}, round({_V} / 1.8, 6) + 0.0 AS p FROM lineitem")
def prox_ridge(spark: SparkSession, d: str) -> DataFrame:
    return _prox(spark, d, lambda v, y: prox.prox_ridge_col(v, 0.4))


@query(f"SELECT {_LI}, round({_SOFT.format(_V, '0.4')}, 6) + 0.0 AS p FROM lineitem")
def prox_lasso(spark: SparkSession, d: str) -> DataFrame:
    return _prox(spark, d, lambda v, y: prox.prox_lasso_col(v, 0.4))


@query(
    "WITH p AS (SELECT vec_id, embedding[1]::DOUBLE AS o, embedding[2]::DOUBLE AS a, embedding[3]::DOUBLE AS b, embedding[4]::DOUBLE AS c FROM embeddings), s AS (SELECT *, (o - (a + b + c)) / 4 AS g FROM p) "
    "SELECT vec_id, round(o - g, 6) + 0.0 AS total, round(a + g, 6) + 0.0 AS first_part, round(abs((o - g) - (a + b + c + 3 * g)), 6) + 0.0 AS gap FROM s"
)
def exchange_projection(spark: SparkSession, d: str) -> DataFrame:
    """The projection that shares a gap between outputs and their parts, in one Arrow pass."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            v = np.array(b.column(1).to_pylist(), float).reshape(b.num_rows, -1)
            total, parts = prox.exchange(v[:, 0], [v[:, k] for k in (1, 2, 3)])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(total), pa.array(parts[0]), pa.array(np.abs(total - sum(parts)))], names=["vec_id", "total", "first_part", "gap"])

    src = table(spark, d, "embeddings").select("vec_id", F.slice("embedding", 1, 4).alias("v"))
    out = src.mapInArrow(run, "vec_id long, total double, first_part double, gap double")
    return out.select("vec_id", *(r6(c).alias(c) for c in ("total", "first_part", "gap")))


@query(
    "WITH v AS (SELECT embedding[1:4]::DOUBLE[] AS e FROM embeddings) SELECT i::INT - 1 AS i, j::INT - 1 AS j, round(sum(e[i] * e[j]), 6) + 0.0 AS v FROM v, range(1, 5) a(i), range(1, 5) b(j) GROUP BY ALL"
)
def normal_equation_parts(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.baselines.ridge import normal_equations

    src = _vectors(spark, d).select(F.slice("x", 1, 4).alias("x"), F.array(F.lit(0.0)).alias("y"))
    g, _, _ = normal_equations(src, identity_map(4))
    rows = [(i, j, float(g[i, j])) for i in range(4) for j in range(4)]
    return spark.createDataFrame(rows, "i int, j int, v double").select("i", "j", r6("v").alias("v"))


def _charge_examples(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem")
    return li.select(F.array(F.col("l_quantity") / 50, F.col("l_discount") * 10).alias("x"), F.array(F.col("l_extendedprice") / 10000).alias("y"))


_CRAMER = (
    "m AS (SELECT count(*) AS n, sum(z0 * z0) AS a, sum(z0 * z1) AS b, sum(z1 * z1) AS c, sum(z0 * y) AS p, sum(z1 * y) AS q FROM z), "
    f"r AS (SELECT a + n * {LAM} AS a, b, c + n * {LAM} AS c, p, q FROM m) "
    "SELECT 0 AS feature, round((p * c - b * q) / (a * c - b * b), {0}) + 0.0 AS w FROM r UNION ALL SELECT 1, round((a * q - b * p) / (a * c - b * b), {0}) + 0.0 FROM r"
)


@query("WITH z AS (SELECT l_quantity / 50 AS z0, l_discount * 10 AS z1, l_extendedprice / 10000 AS y FROM lineitem), " + _CRAMER.format(6))
def linear_ridge_2d(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.baselines.ridge import linear_ridge

    w = linear_ridge(_charge_examples(spark, d), LAM, 2).matrix[:, 0]
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate(w)], "feature int, w double").select("feature", r6("w").alias("w"))


_SMALL_SEED = 3
_SMALL_Z = ", ".join(
    f"cos(8 * embedding[1]::DOUBLE * {portable_normal_sql(_SMALL_SEED, '0', str(q), 'duckdb')} + 8 * embedding[2]::DOUBLE * {portable_normal_sql(_SMALL_SEED, '1', str(q), 'duckdb')} + {math.pi!r}::DOUBLE * {portable_uniform_sql(_SMALL_SEED, '2', str(2 * q), 'duckdb')}) AS z{q}"
    for q in (0, 1)
)
_SMALL = f"z AS (SELECT vec_id, vec_id % 2 AS r, {_SMALL_Z}, CASE WHEN embedding[1]::DOUBLE * embedding[2]::DOUBLE > 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM embeddings)"


def _small_map(cols: int = 2) -> FourierMap:
    return FourierMap(2, 2, cols, _SMALL_SEED, sigma=1.0, generator="portable")


def _small_examples(spark: SparkSession, d: str) -> DataFrame:
    return prep.embedding_task(table(spark, d, "embeddings"), "xor01").withColumn("row_block", F.pmod("row_id", F.lit(2)))


@query(f"WITH {_SMALL}, " + _CRAMER.format(6))
def rff_ridge_2d(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.baselines.ridge import feature_ridge

    w = feature_ridge(_small_examples(spark, d), _small_map(), LAM).matrix[:, 0]
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate(w)], "feature int, w double").select("feature", r6("w").alias("w"))


@query(f"WITH {_SMALL}, " + _CRAMER.format(3))
def admm_converged_2d(spark: SparkSession, d: str) -> DataFrame:
    """The block solver on two row and two column blocks, run until it stands."""
    from kernelblocks.admm.engine import solve

    ex = _small_examples(spark, d).persist()
    n = ex.count()
    # the models' step grows with the rows, so that the rounds to the optimum don't
    w = solve(ex, _small_map(), "squared", "ridge", LAM, rho=3.0 / n, rows=2, iters=120, checkpoint_every=10, weight_pull=n / 10).model.matrix[:, 0]
    ex.unpersist()
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate(w)], "feature int, w double").select("feature", r6("w", 3).alias("w"))


_PATH_ROUNDS = 5


def _path_sql(rounds: int) -> str:
    """The first rounds of the solver written out: a set of tables for each round, from the derivation and not from the code."""
    ctes = [
        "p AS MATERIALIZED (SELECT count(*) AS n, 1.0::DOUBLE / count(*) AS rho FROM z)",
        "q AS MATERIALIZED (SELECT r, 1 / (sum(z0 * z0) + 1) AS q0, 1 / (sum(z1 * z1) + 1) AS q1, sum(z0 * z0) AS g0, sum(z1 * z1) AS g1 FROM z GROUP BY r)",
        "x0 AS (SELECT vec_id, r, z0, z1, y, 0.0::DOUBLE AS ob, 0.0::DOUBLE AS nu, 0.0::DOUBLE AS gap FROM z)",
        "b0 AS (SELECT r, 0.0::DOUBLE AS w0, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS u0, 0.0::DOUBLE AS u1, 0.0::DOUBLE AS m0, 0.0::DOUBLE AS m1 FROM q)",
        "t0 AS (SELECT 0.0::DOUBLE AS c0, 0.0::DOUBLE AS c1, 0.0::DOUBLE AS w0, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS m0, 0.0::DOUBLE AS m1)",
    ]
    for k in range(1, rounds + 1):
        o = k - 1
        ctes += [
            # duals catch up with the consensus, then the root's prox
            f"d{k} AS MATERIALIZED (SELECT c0, c1, m0 + w0 - c0 AS m0, m1 + w1 - c1 AS m1 FROM t{o})",
            f"e{k} AS MATERIALIZED (SELECT *, (c0 - m0) / (1 + 2 * {LAM} / rho) AS w0, (c1 - m1) / (1 + 2 * {LAM} / rho) AS w1 FROM d{k}, p)",
            f"a{k} AS MATERIALIZED (SELECT r, sum(z0 * (gap / 3 + nu)) AS a0, sum(z1 * (gap / 3 + nu)) AS a1 FROM x{o} GROUP BY r)",
            f"f{k} AS MATERIALIZED (SELECT b.r, b.m0 + b.w0 - e.c0 AS m0, b.m1 + b.w1 - e.c1 AS m1, b.u0, b.u1, a0, a1, q0, q1, g0, g1, e.c0, e.c1 FROM b{o} b JOIN a{k} a ON a.r = b.r JOIN q ON q.r = b.r, e{k} e)",
            f"h{k} AS MATERIALIZED (SELECT *, q0 * (c0 - m0 + u0 + a0) AS w0, q1 * (c1 - m1 + u1 + a1) AS w1 FROM f{k})",
            f"b{k} AS MATERIALIZED (SELECT r, w0, w1, g0 * w0 AS u0, g1 * w1 AS u1, m0, m1 FROM h{k})",
            # squared loss with kappa = 1/(n rho) = 1
            f"y{k} AS MATERIALIZED (SELECT vec_id, x.r, z0, z1, y, nu, (ob - nu + 2 * y) / 3 AS o, z0 * w0 + z1 * w1 AS s FROM x{o} x JOIN b{k} b ON b.r = x.r)",
            f"x{k} AS MATERIALIZED (SELECT vec_id, r, z0, z1, y, 2 * o / 3 + s / 3 AS ob, nu + o - (2 * o / 3 + s / 3) AS nu, o - s AS gap FROM y{k})",
            f"t{k} AS MATERIALIZED (SELECT (any_value(e.w0) + sum(b.w0)) / 3 AS c0, (any_value(e.w1) + sum(b.w1)) / 3 AS c1, any_value(e.w0) AS w0, any_value(e.w1) AS w1, any_value(e.m0) AS m0, any_value(e.m1) AS m1 FROM b{k} b, e{k} e)",
        ]
    out = " UNION ALL ".join(f"SELECT {k} AS iter, {j} AS feature, round(c{j}, 6) + 0.0 AS w FROM t{k}" for k in range(1, rounds + 1) for j in (0, 1))
    # the first round has no dual to catch up: all of its terms are zero
    return f"WITH {_SMALL}, " + ", ".join(ctes) + " " + out


@query(_path_sql(_PATH_ROUNDS))
def admm_trajectory_small(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.admm.engine import solve

    run = solve(_small_examples(spark, d), _small_map(), "squared", "ridge", LAM, rows=2, iters=_PATH_ROUNDS, keep_trajectory=True)
    rows = [(k + 1, j, float(w[j, 0])) for k, w in enumerate(run.trajectory) for j in (0, 1)]
    return spark.createDataFrame(rows, "iter int, feature int, w double").select("iter", "feature", r6("w").alias("w"))


@query(f"WITH {_SMALL}, o AS (SELECT y, 0.7 * z0 - 0.4 * z1 AS o FROM z) SELECT round(avg(greatest(0, 1 - o * y)) + {LAM} * (0.49 + 0.16), 6) AS objective, count(*) AS n FROM o")
def objective_value(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.admm.engine import Model, objective

    ex = _small_examples(spark, d)
    model = Model(_small_map(), [np.array([[0.7]]), np.array([[-0.4]])])
    # the weights above are for cosines of amplitude 1, which is the unit scale for two features
    value = objective(ex, model, "hinge", "ridge", LAM)
    return ex.agg(F.count("*").alias("n")).select(F.round(F.lit(value), 6).alias("objective"), "n")


_PLANS = ((784, 10, 100_000, 200, 20, 6), (440, 147, 528_000, 1000, 256, 64), (64, 1, 1024, 16, 4, 1))
_PLAN_SQL = "WITH n AS (SELECT count(*)::DOUBLE AS n FROM lineitem), p(d, m, s, c, r, t) AS (VALUES " + ", ".join(str(tuple(float(v) for v in p)) for p in _PLANS).replace(".0", "::DOUBLE") + ") "


def _per_plan(spark: SparkSession, d: str, row, schema: str) -> DataFrame:
    n = table(spark, d, "lineitem").count()
    df = spark.createDataFrame([row(n, *p) for p in _PLANS], schema)
    return df.select(*(F.round(c, 3).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes))


@query(
    _PLAN_SQL + "SELECT s::BIGINT AS s, r::BIGINT AS r, round(n * (m + d) / r, 3) AS data, round(5 * s * m, 3) AS model_state, round(4 * n * m / r, 3) AS output_state, round(s * s / c, 3) AS factors, "
    "round(n * (m + d) / r + 5 * s * m + 4 * n * m / r + t * (n * s / (r * c) + m * s / c) + (t + 1) * n * m / r + s * s / c, 3) AS total FROM n, p"
)
def memory_model(spark: SparkSession, d: str) -> DataFrame:
    def row(n, dd, m, s, c, r, t):
        got = blockplan.memory_model(n, m, dd, s, c, r, r, t)
        return (s, r, *(float(got[k]) for k in ("data", "model_state", "output_state", "factors", "total")))

    return _per_plan(spark, d, row, "s long, r long, data double, model_state double, output_state double, factors double, total double")


@query(_PLAN_SQL + "SELECT s::BIGINT AS s, round(n * d * s, 3) AS transform, round(n * m * c, 3) AS sums, round(r * s * s * m / c, 3) AS solves, round(3 * n * s * m, 3) AS products FROM n, p")
def flop_model(spark: SparkSession, d: str) -> DataFrame:
    def row(n, dd, m, s, c, r, t):
        got = blockplan.flop_model(n, m, dd, s, c, r)
        return (s, *(float(got[k]) for k in ("transform", "sums", "solves", "products")))

    return _per_plan(spark, d, row, "s long, transform double, sums double, solves double, products double")


@query(_PLAN_SQL + "SELECT s::BIGINT AS s, round(8 * s * m, 3) AS buffer, round(16 * s * m * log2(r), 3) AS round_bytes, round(8 * n * s, 3) AS materialized FROM n, p")
def comm_model(spark: SparkSession, d: str) -> DataFrame:
    def row(n, dd, m, s, c, r, t):
        got = blockplan.comm_model(s, m, r)
        return (s, got["buffer"], got["round"], blockplan.materialized_bytes(n, s))

    return _per_plan(spark, d, row, "s long, buffer double, round_bytes double, materialized double")


_RUNS = "WITH t AS (SELECT l_returnflag AS series, l_linenumber AS resources, sum(l_extendedprice) / l_linenumber AS seconds FROM lineitem GROUP BY l_returnflag, l_linenumber) "


@query(
    _RUNS + "SELECT series, resources, round(first_value(seconds) OVER w / seconds, 6) AS speedup, round(first_value(seconds) OVER w / seconds / (resources / first_value(resources) OVER w), 6) AS efficiency, "
    "round(seconds / first_value(seconds) OVER w, 6) AS ratio FROM t WINDOW w AS (PARTITION BY series ORDER BY resources ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
)
def scaling_measures(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.measures import scaling_table, weak_table

    runs = table(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("series"), F.col("l_linenumber").alias("resources")).agg(F.sum("l_extendedprice").alias("s"))
    runs = runs.select("series", "resources", (F.col("s") / F.col("resources")).alias("seconds"))
    both = weak_table(scaling_table(runs))
    return both.select("series", "resources", *(r6(c).alias(c) for c in ("speedup", "efficiency", "ratio")))


@query(
    "WITH t AS (SELECT event_type AS step, (user_id % 4)::INT AS row_block, sum(value) AS sec FROM events GROUP BY ALL UNION ALL SELECT 'round', (user_id % 4)::INT, sum(value) FROM events GROUP BY 2), "
    "s AS (SELECT step, min(sec) AS lo, max(sec) AS hi, avg(sec) AS mid FROM t GROUP BY step) "
    "SELECT step, round(lo, 4) AS min_sec, round(hi, 4) AS max_sec, round(mid, 4) AS avg_sec, round(100 * hi / (SELECT hi FROM s WHERE step = 'round'), 4) AS share FROM s"
)
def breakdown_aggregate(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.measures import step_profile

    ev = table(spark, d, "events").withColumn("row_block", F.pmod("user_id", F.lit(4)).cast("int"))
    times = ev.select(F.col("event_type").alias("step"), "row_block", F.col("value").alias("sec"))
    both = times.union(ev.select(F.lit("round"), "row_block", "value"))
    return step_profile(both).select("step", *(r6(c, 4).alias(c) for c in ("min_sec", "max_sec", "avg_sec", "share")))
