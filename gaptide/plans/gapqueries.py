"""Registered queries of layouts, products, gaps, selection, measures, block steps, bounds: plans that SQL can repeat."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..common import cut, hash32, table, unit_draw
from ..functions import objectives as O
from ..operators import gaps as G
from ..operators import layout as L
from ..operators import metrics as M
from ..operators import select as S
from ..operators import theory
from ..sources import features as X
from . import sqlparts as Q

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
c = F.col


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return put


def r6(x: Column | str) -> Column:
    """Six decimals; minus zero becomes zero."""
    return F.round(c(x) if isinstance(x, str) else x, 6) + F.lit(0.0)


BOX = 10.0


def model_objective(model: str):
    make = {"ridge": lambda: O.RidgePrimal(0.5), "lasso": lambda: O.LassoBoxed(0.3, box=BOX), "enet": lambda: O.ElasticNet(0.3, lam2=0.7), "logit_l1": lambda: O.LogisticL1(0.3, box=BOX), "ridge_dual": lambda: O.RidgeDual(0.5), "svm": lambda: O.HingeSvmDual(1.0), "sqhinge": lambda: O.SquaredHingeSvmDual(1.0), "logit_dual": lambda: O.LogisticDual(1.0)}
    return make[model]()


def cells(spark: SparkSession, sf_dir: str, model: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Triples, targets (row_id, b) and weights (coord_id, alpha, y) of a model's problem on the embeddings."""
    e = table(spark, sf_dir, "embeddings")
    sign = F.when(c("label") < 5, 1.0).otherwise(-1.0)
    if Q.MODELS[model][0] == "features":
        coo = X.emb_cells(spark, sf_dir)
        tgt = e.select(c("vec_id").alias("row_id"), (unit_draw("b", c("vec_id")) * 2 - 1).alias("b"))
        al = spark.range(64).select(c("id").alias("coord_id"), (unit_draw("a", c("id")) * 2 - 1).alias("alpha"), F.lit(0.0).alias("y"))
        return coo, tgt, al
    scale = sign if Q.MODELS[model][0] == "signed" else F.lit(1.0)
    coo = e.select(c("vec_id").alias("coord_id"), scale.alias("s"), F.posexplode("embedding").alias("p", "x")).select("coord_id", c("p").cast("long").alias("row_id"), (c("x").cast("double") * c("s")).alias("x"))
    tgt = spark.range(64).select(c("id").alias("row_id"), F.lit(0.0).alias("b"))
    al = e.select(c("vec_id").alias("coord_id"), unit_draw("a", c("vec_id")).alias("alpha"), sign.alias("y"))
    return coo, tgt, al


def dual_rows(model: str, val: DataFrame, tgt: DataFrame) -> DataFrame:
    """row_id, w and f from v and b."""
    v, b, s = c("v"), c("b"), F.signum("b")
    lam = getattr(model_objective(model), "lam")
    if model == "logit_l1":
        w, f = -s / (1 + F.exp(s * v)), F.log(1 + F.exp(-s * v))
    elif Q.MODELS[model][0] == "features":
        w, f = v - b, (v - b) * (v - b) * 0.5
    else:
        w, f = v / lam, v * v / (2 * lam)
    return val.join(tgt, "row_id").select("row_id", w.alias("w"), f.alias("f"))


def problem(spark: SparkSession, sf_dir: str, model: str, zero: bool = False) -> tuple[DataFrame, DataFrame]:
    """Gaps (coord_id, alpha, y, u, norm2, gap, g) and rows (row_id, w, f), as one lazy plan."""
    obj = model_objective(model)
    coo, tgt, al = cells(spark, sf_dir, model)
    if zero:
        al = al.withColumn("alpha", F.lit(0.0))
    val = coo.join(al, "coord_id").groupBy("row_id").agg(F.sum(c("x") * c("alpha")).alias("v"))
    dual = dual_rows(model, val, tgt)
    u = coo.join(dual, "row_id").groupBy("coord_id").agg(F.sum(c("x") * c("w")).alias("u"), F.sum(c("x") * c("x")).alias("norm2"))
    out = u.join(al, "coord_id")
    return out.select("coord_id", "alpha", "y", "u", "norm2", obj.gap_col(c("alpha"), c("u"), c("y")).alias("gap"), obj.g_col(c("alpha"), c("y")).alias("g")), dual


def _gap_query(model: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        now, _ = problem(spark, sf_dir, model)
        start, _ = problem(spark, sf_dir, model, zero=True) if model != "logit_dual" else (None, None)
        out = now.select("coord_id", r6("u").alias("u"), r6("gap").alias("gap"))
        return out if start is None else out.join(start.select("coord_id", r6("gap").alias("gap_start")), "coord_id")

    sql = Q.products(model)
    if model == "logit_dual":
        query(sql + "SELECT coord_id, round(u, 6) + 0.0 AS u, round(gap, 6) + 0.0 AS gap FROM pg", f"gap_{model}")(run)
    else:
        start = Q.steps(model, "0.0", "0")
        query(sql + f", {start} SELECT pg.coord_id, round(pg.u, 6) + 0.0 AS u, round(pg.gap, 6) + 0.0 AS gap, round(pg0.gap, 6) + 0.0 AS gap_start FROM pg JOIN pg0 USING (coord_id)", f"gap_{model}")(run)

    def value(spark: SparkSession, sf_dir: str) -> DataFrame:
        now, dual = problem(spark, sf_dir, model)
        f, g = dual.agg(F.sum("f").alias("f")), now.agg(F.sum("g").alias("g"), F.sum("gap").alias("gap_total"))
        return f.crossJoin(g).select(r6(c("f") + c("g")).alias("objective"), r6("gap_total").alias("gap_total"))

    query(sql + "SELECT round((SELECT sum(f) FROM dual) + sum(g), 6) + 0.0 AS objective, round(sum(gap), 6) + 0.0 AS gap_total FROM pg", f"objective_{model}")(value)


for _m in Q.MODELS:
    _gap_query(_m)


# --- layouts and products

EMB = "WITH coo AS (SELECT vec_id AS row_id, unnest(generate_series(0, 63))::BIGINT AS coord_id, unnest(embedding)::DOUBLE AS x FROM embeddings)"


@query(EMB + " SELECT coord_id, row_id, round(x, 6) + 0.0 AS x FROM coo")
def coo_embeddings(spark, sf_dir):
    return X.emb_cells(spark, sf_dir).select("coord_id", "row_id", r6("x").alias("x"))


@query(EMB + " SELECT coord_id, round(sum(x * x), 6) AS norm2 FROM coo GROUP BY 1")
def norms_embeddings(spark, sf_dir):
    return G.norms(X.emb_cells(spark, sf_dir), "coo").select("coord_id", r6("norm2").alias("norm2"))


DOC_TF = r"""WITH t AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token FROM documents),
tf AS (SELECT doc_id, token, count(*)::DOUBLE AS x FROM t WHERE token <> '' GROUP BY 1, 2),
ids AS (SELECT token, row_number() OVER (ORDER BY token) - 1 AS coord_id FROM (SELECT token FROM tf GROUP BY token HAVING count(*) >= 5)),
coo AS (SELECT coord_id, token, doc_id AS row_id, x FROM tf JOIN ids USING (token) WHERE doc_id IN (SELECT doc_id FROM labels))"""


@query(DOC_TF + " SELECT coord_id, token, row_id, x FROM coo")
def coo_documents(spark, sf_dir):
    return X.doc_tf(spark, sf_dir)


@query(DOC_TF + " SELECT coord_id, sum(x * x) AS norm2 FROM coo GROUP BY 1")
def norms_documents(spark, sf_dir):
    return G.norms(X.doc_tf(spark, sf_dir), "coo").select("coord_id", "norm2")


@query(f"SELECT doc_id AS row_id, pmod AS coord_id, sum(s)::DOUBLE AS x FROM (SELECT doc_id, h % 4096 AS pmod, CASE WHEN h >= 2147483648 THEN 1.0 ELSE -1.0 END AS s FROM (SELECT doc_id, ('0x' || substr(md5('tok:' || token), 1, 8))::BIGINT AS h FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{{L}}]+')) AS token FROM documents) WHERE token <> '')) GROUP BY 1, 2")
def hashed_documents(spark, sf_dir):
    return X.doc_hash(spark, sf_dir)


def fixed_w(n: int) -> np.ndarray:
    from ..common import hash32_py

    return np.array([(hash32_py("w", i) + 0.5) / (1 << 32) * 2 - 1 for i in range(n)])


W_SQL = f"WITH coo AS (SELECT vec_id AS coord_id, unnest(generate_series(0, 63))::BIGINT AS row_id, unnest(embedding)::DOUBLE AS x FROM embeddings) SELECT coord_id, round(sum(x * ({Q.draw('w', 'row_id')} * 2 - 1)), 6) + 0.0 AS u FROM coo GROUP BY 1"


def _dots(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, w = X.emb_samples(spark, sf_dir).select("coord_id", "vals"), fixed_w(64)
        if kind == "dense":
            out = G.dots(e, w)
        elif kind == "sql":
            out = G.dots_sql(e, w)
        elif kind == "sparse":
            out = G.dots(L.to_sparse(L.to_coo(e, "dense")), w, "sparse")
        elif kind == "chunked":
            out = G.dots(L.to_chunked(L.to_coo(e, "dense"), 16), w, "chunked", 16)
        else:
            out = G.dots(L.to_coo(e, "dense"), w, "coo")
        return out.select("coord_id", r6("u").alias("u"))

    query(W_SQL, f"dots_{kind}")(run)


for _k in ("dense", "sql", "sparse", "chunked", "coo"):
    _dots(_k)


@query("WITH e AS (SELECT unnest(generate_series(0, 63))::BIGINT AS coord_id, unnest(embedding)::DOUBLE AS x FROM embeddings) SELECT coord_id, round(avg(x), 6) + 0.0 AS mean, round(stddev_samp(x), 6) AS sd FROM e GROUP BY 1")
def standardize_stats(spark, sf_dir):
    return X.emb_cells(spark, sf_dir).groupBy("coord_id").agg(r6(F.avg("x")).alias("mean"), r6(F.stddev("x")).alias("sd"))


@query("""WITH e AS (SELECT vec_id, unnest(generate_series(0, 63)) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings),
p AS (SELECT a.i AS i, b.i AS j, a.vec_id, a.x * b.x AS x FROM e a JOIN e b USING (vec_id) WHERE a.i <= b.i)
SELECT i::BIGINT AS i, count(*) AS n, round(sum(x), 6) + 0.0 AS total, round(sum(x * x), 6) AS squares FROM p GROUP BY 1""")
def poly2_stats(spark, sf_dir):
    rows = table(spark, sf_dir, "embeddings").select(F.posexplode(X.poly2(c("embedding").cast("array<double>"))).alias("p", "x")).where("p >= 64")
    ends = F.lit([64 + sum(64 - k for k in range(i)) for i in range(65)])
    i = F.size(F.filter(ends, lambda e: e <= c("p"))) - 1
    return rows.groupBy(i.cast("long").alias("i")).agg(F.count(F.lit(1)).alias("n"), r6(F.sum("x")).alias("total"), r6(F.sum(c("x") * c("x"))).alias("squares"))


@query(Q.products("lasso") + "SELECT row_id, round(v, 6) + 0.0 AS v FROM val")
def rebuild_v(spark, sf_dir):
    coo, _, al = cells(spark, sf_dir, "lasso")
    return G.weighted_rows(coo, al, "coo").select("row_id", r6("v").alias("v"))


@query(Q.products("svm") + ", n AS (SELECT count(*) AS n, sum(gap) AS total, max(gap) AS greatest, quantile_cont(gap, 0.5) AS median, quantile_cont(gap, 0.9) AS p90 FROM pg) SELECT n, round(total, 6) AS total, round(greatest, 6) AS greatest, round(median, 6) AS median, round(p90, 6) AS p90 FROM n")
def gap_profile(spark, sf_dir):
    return G.gap_profile(problem(spark, sf_dir, "svm")[0]).select("n", *[r6(x).alias(x) for x in ("total", "greatest", "median", "p90")])


@query(Q.products("ridge") + "SELECT round((SELECT sum(f) FROM dual) + (SELECT sum(0.5 * w * w + w * b) FROM dual) + sum(g + u * u), 6) AS pair_gap, round(sum(gap), 6) AS gap_total FROM pg")
def pair_gap(spark, sf_dir):
    """The general gap at the dual point equals the sum of coordinate gaps."""
    now, dual = problem(spark, sf_dir, "ridge")
    _, tgt, _ = cells(spark, sf_dir, "ridge")
    left = dual.join(tgt, "row_id").agg(F.sum(c("f") + c("w") * c("w") * 0.5 + c("w") * c("b")).alias("l"))
    return left.crossJoin(now.agg(F.sum(c("g") + model_objective("ridge").conj_col(-c("u"), c("y"))).alias("r"), F.sum("gap").alias("t"))).select(r6(c("l") + c("r")).alias("pair_gap"), r6("t").alias("gap_total"))


# --- selection: keys are rounded before they are ordered, so that both engines see the same ties

STATE = Q.products("svm") + ", st AS (SELECT coord_id, round(gap, 9) AS gap, round(gap, 9) * (0.5 + " + Q.draw("z", "coord_id") + ") AS z0, norm2, alpha, u, round(u, 9) AS slope, " + Q.draw("r", "coord_id") + " < 0.25 AS resident, (" + Q.hash32("'k:' || coord_id") + " % 8)::INT AS bucket FROM pg), sv AS (SELECT *, round(z0, 9) AS z, round(norm2, 6) AS nn FROM st)"
M_SQL = "(SELECT floor(count(*) * 0.25)::BIGINT FROM sv)"


def state_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    now, _ = problem(spark, sf_dir, "svm")
    gap = F.round("gap", 9)
    return now.select("coord_id", gap.alias("gap"), F.round(gap * (0.5 + unit_draw("z", c("coord_id"))), 9).alias("z"), F.round("norm2", 6).alias("norm2"), "alpha", "u", F.round("u", 9).alias("slope"), (unit_draw("r", c("coord_id")) < 0.25).alias("resident"), F.pmod(hash32("k", c("coord_id")), F.lit(8)).cast("int").alias("bucket"))


def _select(name: str, rule: str, sql: str, round: int = 3, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        state = cut(state_table(spark, sf_dir))
        n = state.count()
        return S.select_block(rule, state, S.block_size(n, 0.25), round, seed=7, n=n, **options).select("coord_id")

    query(STATE + " " + sql, name)(run)


def _top(key: str) -> str:
    return f"SELECT coord_id FROM sv ORDER BY {key} DESC, coord_id LIMIT {M_SQL}"


R_SQL = f"((({Q.hash32(chr(39) + '7:3:' + chr(39) + ' || coord_id')}) + 0.5) / 4294967296.0)"
_select("select_fresh", "fresh_gap", _top("gap"))
_select("select_memory", "gap_memory", _top("z"))
_select("select_steepest", "steepest", _top("abs(slope)"))
_select("select_sticky", "sticky", _top("CASE WHEN resident THEN z * 1.1 ELSE z END"))
_select("select_random", "random", f"SELECT coord_id FROM sv ORDER BY {Q.hash32(chr(39) + '7:3:' + chr(39) + ' || coord_id')}, coord_id LIMIT {M_SQL}")
_select("select_importance", "importance_norm", _top(f"CASE WHEN nn > 0 THEN round(ln({R_SQL}) / sqrt(nn), 9) ELSE -1e300 END"))
_select("select_importance_norm2", "importance_norm2", _top(f"CASE WHEN nn > 0 THEN round(ln({R_SQL}) / nn, 9) ELSE -1e300 END"))
_select("select_importance_gap", "importance_gap", _top(f"CASE WHEN z > 0 THEN round(ln({R_SQL}) / z, 9) ELSE -1e300 END"))
_select("select_single", "single", "SELECT coord_id FROM sv ORDER BY gap DESC, coord_id LIMIT 1")
_select("select_sequential", "sequential", f"SELECT coord_id FROM sv WHERE (coord_id - 3 * {M_SQL} + 4 * (SELECT count(*) FROM sv)) % (SELECT count(*) FROM sv) < {M_SQL}")
_select("select_uniform_batches", "uniform_batches", f"SELECT coord_id FROM (SELECT coord_id, row_number() OVER (ORDER BY {Q.hash32(chr(39) + '7:e0:' + chr(39) + ' || coord_id')}, coord_id) - 1 AS r FROM sv) WHERE r >= 3 * {M_SQL} AND r < 4 * {M_SQL}")
_select("select_keep_informative", "keep_informative", f"SELECT coord_id FROM sv ORDER BY CASE WHEN resident AND ((alpha > 0 AND alpha < 1) OR u < 1) THEN 0 ELSE 1 END, (coord_id - 3 * {M_SQL} + 4 * (SELECT count(*) FROM sv)) % (SELECT count(*) FROM sv) LIMIT {M_SQL}")
_select("select_partition_top", "partition_local_top", f"SELECT coord_id FROM (SELECT coord_id, row_number() OVER (PARTITION BY bucket ORDER BY z DESC, coord_id) AS r, ceil(count(*) OVER (PARTITION BY bucket) * ({M_SQL}::DOUBLE / (SELECT count(*) FROM sv))) AS q FROM sv) WHERE r <= q")


@query(STATE + " " + _top("z"))
def topm_threshold(spark, sf_dir):
    state = cut(state_table(spark, sf_dir))
    return S.top_threshold(state, c("z"), S.block_size(state.count(), 0.25))


@query(STATE + f", s AS (SELECT coord_id FROM sv ORDER BY {Q.hash32(chr(39) + '7:r1:' + chr(39) + ' || coord_id')}, coord_id LIMIT (SELECT ceil(count(*) * 0.05)::BIGINT FROM sv)) SELECT coord_id, CASE WHEN s.coord_id IS NOT NULL THEN gap ELSE z END AS z, (s.coord_id IS NOT NULL)::INT AS z_round FROM sv LEFT JOIN s USING (coord_id)")
def refresh_z_5pct(spark, sf_dir):
    """The gap memory after a round that refreshes a twentieth of it."""
    state = cut(state_table(spark, sf_dir))
    k = -(-state.count() * 5 // 100)
    sample = state.select("coord_id", hash32(7, "r1", c("coord_id")).alias("h")).orderBy("h", "coord_id").limit(k).select("coord_id", F.lit(1).alias("hit"))
    return state.join(sample, "coord_id", "left").select("coord_id", F.when(c("hit").isNotNull(), c("gap")).otherwise(c("z")).alias("z"), F.coalesce("hit", F.lit(0)).alias("z_round"))


# --- measures

BLOCK = STATE + f", blk AS ({_top('gap')}), old AS ({_top('z')})"


@query(BLOCK + " SELECT round(avg(gap) FILTER (coord_id IN (SELECT coord_id FROM blk)) / avg(gap), 6) AS rho FROM sv")
def rho_first_block(spark, sf_dir):
    state = cut(state_table(spark, sf_dir))
    block = S.select_block("fresh_gap", state, S.block_size(state.count(), 0.25))
    return M.rho_plan(state.select("coord_id", "gap"), block).select(r6("rho").alias("rho"))


@query(BLOCK + " SELECT count(*) AS swaps, count(*) * 64 * 8 AS bytes_in FROM blk WHERE coord_id NOT IN (SELECT coord_id FROM old)")
def swaps_two_rounds(spark, sf_dir):
    state = cut(state_table(spark, sf_dir))
    m = S.block_size(state.count(), 0.25)
    s = M.swaps(S.select_block("gap_memory", state, m), S.select_block("fresh_gap", state, m))
    return s.select("swaps", (c("swaps") * 64 * 8).alias("bytes_in"))


@query("SELECT round(avg(CASE WHEN abs(alpha) > 0.5 THEN 1.0 ELSE 0.0 END), 6) AS support FROM (SELECT " + Q.draw("a", "vec_id") + " AS alpha FROM embeddings)")
def support_size(spark, sf_dir):
    return M.support_plan(table(spark, sf_dir, "embeddings").select(unit_draw("a", c("vec_id")).alias("alpha")), 0.5).select(r6("support").alias("support"))


@query("SELECT round(avg(10 - age), 6) + 0.0 AS mean_age, max(10 - age) AS max_age FROM (SELECT floor(" + Q.draw("age", "vec_id") + " * 10)::BIGINT AS age FROM embeddings)")
def mean_age(spark, sf_dir):
    made = F.floor(unit_draw("age", c("vec_id")) * 10).cast("long")
    return table(spark, sf_dir, "embeddings").select((10 - made).alias("a")).agg(r6(F.avg("a")).alias("mean_age"), F.max("a").alias("max_age"))


@query("""WITH e AS (SELECT sum(x * x) AS x FROM (SELECT vec_id, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY vec_id),
s AS (SELECT (SELECT round(avg(x), 6) FROM e) AS sigma, count(*)::DOUBLE AS n, floor(count(*) * 0.25) AS m FROM embeddings),
q AS (SELECT *, greatest(0, n / m * ln(2 * 0.8 * m * 3 / (n * (2 * 1 * 100 * sigma)))) AS t0, unnest(generate_series(0, 50))::BIGINT AS t FROM s)
SELECT t, round(pow(1 - 0.8 * m / n * 0.5 / (sigma * 1 + 0.5), t) * 3, 6) AS strong, round(2 * (2 * 1 * 100 * sigma) * n * n / (0.8 * m * (2 * n + t - t0)), 6) AS bounded FROM q""")
def theory_bound_rows(spark, sf_dir):
    """Bounds over rounds for blocks of a quarter of the vectors, whose mean squared length stands for the curvature."""
    x = F.aggregate(c("embedding").cast("array<double>"), F.lit(0.0), lambda s, v: s + v * v)
    sigma, n = table(spark, sf_dir, "embeddings").agg(F.round(F.avg(x), 6), F.count(F.lit(1))).first()
    m, g = S.block_size(n, 0.25), theory.gamma(1, 10, sigma)
    rows = [(t, theory.rate_strong(3, t, 0.8, 1, 0.5, sigma, m, n), theory.rate_bounded(3, t, 0.8, g, m, n)) for t in range(51)]
    return spark.createDataFrame(rows, "t long, strong double, bounded double").select("t", r6("strong").alias("strong"), r6("bounded").alias("bounded"))


# --- block steps as plans: all coordinates at once, at the trace of the matrix (which is above its squared norm)


def _prox(model: str, rounds: int, sql_step: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        obj = model_objective(model)
        coo, tgt, al = cells(spark, sf_dir, model)
        q = coo.agg(F.sum(c("x") * c("x")).alias("q"))
        al = al.withColumn("alpha", F.lit(0.0))
        for _ in range(rounds):
            val = coo.join(al, "coord_id").groupBy("row_id").agg(F.sum(c("x") * c("alpha")).alias("v"))
            u = coo.join(dual_rows(model, val, tgt), "row_id").groupBy("coord_id").agg(F.sum(c("x") * c("w")).alias("u"))
            step = obj.step_col(c("alpha"), c("u"), c("q") * float(obj.smooth), c("y"))
            al = cut(al.join(u, "coord_id").crossJoin(q).select("coord_id", (c("alpha") + step).alias("alpha"), "y"))  # q is one row
        return al.select("coord_id", (F.round("alpha", 9) + F.lit(0.0)).alias("alpha"))

    _, _, grad, _, _ = Q.MODELS[model]
    sql = f"WITH {Q.base(model)}, q AS (SELECT sum(x * x) AS q FROM coo), a0 AS (SELECT coord_id, 0.0::DOUBLE AS alpha, y FROM al)"
    for t in range(1, rounds + 1):
        sql += f""", v{t} AS (SELECT coo.row_id, sum(x * alpha) AS v FROM coo JOIN a{t - 1} USING (coord_id) GROUP BY 1), w{t} AS (SELECT row_id, {grad} AS w FROM v{t} JOIN tgt USING (row_id)),
u{t} AS (SELECT coord_id, sum(x * w) AS u FROM coo JOIN w{t} USING (row_id) GROUP BY 1), a{t} AS (SELECT coord_id, {sql_step} AS alpha, y FROM a{t - 1} JOIN u{t} USING (coord_id), q)"""
    query(sql + f" SELECT coord_id, round(alpha, 9) + 0.0 AS alpha FROM a{rounds}", f"block_prox_{model}_{rounds}")(run)


for _t in (1, 3):
    _prox("ridge", _t, "(q * alpha - u) / (q + 0.5)")
    _prox("lasso", _t, "greatest(-10, least(10, sign(alpha - u / q) * greatest(abs(alpha - u / q) - 0.3 / q, 0)))")
    _prox("svm", _t, "greatest(0, least(1, alpha + (1 - u) / q))")


def _single_cd_sql() -> str:
    sql = f"WITH {Q.base('ridge')}, a0 AS (SELECT coord_id, 0.0::DOUBLE AS alpha FROM al), n2 AS (SELECT coord_id, sum(x * x) AS norm2 FROM coo GROUP BY 1)"
    for t in range(1, 6):
        sql += f""", v{t} AS (SELECT coo.row_id, sum(x * alpha) AS v FROM coo JOIN a{t - 1} USING (coord_id) GROUP BY 1), u{t} AS (SELECT coord_id, sum(x * (v - b)) AS u FROM coo JOIN v{t} USING (row_id) JOIN tgt USING (row_id) GROUP BY 1),
g{t} AS (SELECT coord_id, alpha, u, norm2, round((0.5 * alpha + u) * (0.5 * alpha + u), 9) AS gap FROM a{t - 1} JOIN u{t} USING (coord_id) JOIN n2 USING (coord_id)),
a{t} AS (SELECT coord_id, CASE WHEN coord_id = (SELECT coord_id FROM g{t} ORDER BY gap DESC, coord_id LIMIT 1) THEN (norm2 * alpha - u) / (norm2 + 0.5) ELSE alpha END AS alpha FROM g{t})"""
    return sql + " SELECT coord_id, round(alpha, 6) + 0.0 AS alpha FROM a5 WHERE alpha <> 0"


@query(_single_cd_sql())
def single_cd_5_rounds(spark, sf_dir):
    """Classic coordinate descent as the case of one exact coordinate a round, that of the greatest gap."""
    obj = model_objective("ridge")
    coo, tgt, al = cells(spark, sf_dir, "ridge")
    coo = cut(coo)
    al = al.withColumn("alpha", F.lit(0.0))
    for _ in range(5):
        val = coo.join(al, "coord_id").groupBy("row_id").agg(F.sum(c("x") * c("alpha")).alias("v"))
        u = coo.join(dual_rows("ridge", val, tgt), "row_id").groupBy("coord_id").agg(F.sum(c("x") * c("w")).alias("u"), F.sum(c("x") * c("x")).alias("norm2"))
        state = cut(al.join(u, "coord_id").withColumn("gap", F.round(obj.gap_col(c("alpha"), c("u")), 9)))
        block = S.select_block("single", state, 1).withColumn("hit", F.lit(True))
        step = F.when(c("hit"), obj.step_col(c("alpha"), c("u"), c("norm2"))).otherwise(0.0)
        al = cut(state.join(block, "coord_id", "left").select("coord_id", (c("alpha") + step).alias("alpha"), "y"))
    return al.where("alpha <> 0").select("coord_id", r6("alpha").alias("alpha"))
