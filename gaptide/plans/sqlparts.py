"""Pieces of DuckDB SQL for the gap queries: draws, cells, sums, gaps."""

from __future__ import annotations


def draw(part: str, key: str) -> str:
    return f"((('0x' || substr(md5('{part}:' || {key}::VARCHAR), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


def hash32(key: str) -> str:
    return f"('0x' || substr(md5({key}), 1, 8))::BIGINT"


#: Features of the embeddings as coordinates; a target of each row and weights of each coordinate from draws.
FEATURES = f"""
coo AS (SELECT vec_id AS row_id, unnest(generate_series(0, 63))::BIGINT AS coord_id, unnest(embedding)::DOUBLE AS x FROM embeddings),
tgt AS (SELECT vec_id AS row_id, {draw("b", "vec_id")} * 2 - 1 AS b FROM embeddings),
al AS (SELECT coord_id, {draw("a", "coord_id")} * 2 - 1 AS alpha, 0.0::DOUBLE AS y FROM (SELECT DISTINCT coord_id FROM coo))"""

#: Samples as coordinates, times their sign; weights within 0 and 1.
SAMPLES = f"""
coo AS (SELECT vec_id AS coord_id, unnest(generate_series(0, 63))::BIGINT AS row_id, unnest(embedding)::DOUBLE * SIGN AS x FROM embeddings),
tgt AS (SELECT unnest(generate_series(0, 63))::BIGINT AS row_id, 0.0::DOUBLE AS b),
al AS (SELECT vec_id AS coord_id, {draw("a", "vec_id")} AS alpha, CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END::DOUBLE AS y FROM embeddings)"""

SIGN = "CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END"

#: For each model: where it lives, f and the gradient in v and b, g and the conjugate at -u; constants are fixed.
MODELS = {
    "ridge": ("features", "0.5 * (v - b) * (v - b)", "v - b", "0.25 * alpha * alpha", "u * u"),
    "lasso": ("features", "0.5 * (v - b) * (v - b)", "v - b", "0.3 * abs(alpha)", "10 * greatest(abs(u) - 0.3, 0)"),
    "enet": ("features", "0.5 * (v - b) * (v - b)", "v - b", "0.3 * abs(alpha) + 0.35 * alpha * alpha", "greatest(abs(u) - 0.3, 0) * greatest(abs(u) - 0.3, 0) / 1.4"),
    "logit_l1": ("features", "ln(1 + exp(-sign(b) * v))", "-sign(b) / (1 + exp(sign(b) * v))", "0.3 * abs(alpha)", "10 * greatest(abs(u) - 0.3, 0)"),
    "ridge_dual": ("plain", "v * v", "v * 2", "0.5 * alpha * alpha - y * alpha", "0.5 * (y - u) * (y - u)"),
    "svm": ("signed", "0.5 * v * v", "v", "-alpha", "greatest(0, 1 - u)"),
    "sqhinge": ("signed", "0.5 * v * v", "v", "alpha * alpha / 4 - alpha", "greatest(0, 1 - u) * greatest(0, 1 - u)"),
    "logit_dual": ("signed", "0.5 * v * v", "v", "alpha * ln(alpha) + (1 - alpha) * ln(1 - alpha)", "ln(1 + exp(-u))"),
}


def base(model: str) -> str:
    kind = MODELS[model][0]
    return FEATURES if kind == "features" else SAMPLES.replace("SIGN", "1.0" if kind == "plain" else SIGN)


def steps(model: str, alpha: str = "alpha", tag: str = "") -> str:
    """Common tables val, dual, pr and pg (coord_id, alpha, y, u, norm2, gap, g) at an expression of the drawn weights."""
    _, f, grad, g, conj = MODELS[model]
    return f"""val{tag} AS (SELECT coo.row_id, sum(x * ({alpha})) AS v FROM coo JOIN al USING (coord_id) GROUP BY 1),
dual{tag} AS (SELECT row_id, v, b, {grad} AS w, {f} AS f FROM val{tag} JOIN tgt USING (row_id)),
pr{tag} AS (SELECT coord_id, sum(x * w) AS u, sum(x * x) AS norm2 FROM coo JOIN dual{tag} USING (row_id) GROUP BY 1),
pg{tag} AS (SELECT coord_id, alpha, y, u, norm2, greatest(alpha * u + {g} + {conj}, 0) AS gap, {g} AS g FROM (SELECT coord_id, {alpha} AS alpha, y FROM al) JOIN pr{tag} USING (coord_id))
"""


def products(model: str) -> str:
    return f"WITH {base(model)}, {steps(model)}"
