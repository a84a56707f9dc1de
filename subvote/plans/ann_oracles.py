"""SQL forms of the queries in `ann`, built from shared table expressions."""

from __future__ import annotations

import math

DIM, M, K, TOP, RATIO = 64, 8, 8, 10, 0.2


def _points(vec: str = "CAST(embedding AS DOUBLE[])") -> str:
    return f"""
points AS (SELECT vec_id AS id, {vec} AS vec FROM embeddings),
pd AS (SELECT id, unnest(vec) AS x, generate_subscripts(vec, 1) - 1 AS j FROM points),
base AS (SELECT * FROM points WHERE id % 10 <> 0), bd AS (SELECT * FROM pd WHERE id % 10 <> 0),
q AS (SELECT * FROM points WHERE id % 10 = 0), qd AS (SELECT * FROM pd WHERE id % 10 = 0),
size AS (SELECT count(*) AS n FROM base)"""


_BOOKS = f"""
cb AS (
  SELECT b.j // 8 AS subspace, (b.j // 4) % 2 AS half, c.range AS code, b.j % 4 AS t, b.j, b.x
  FROM (SELECT id, row_number() OVER (ORDER BY id) - 1 AS r FROM base) o JOIN size ON true
  JOIN range({K}) c ON o.r = (c.range * n) // {K} JOIN bd b ON b.id = o.id
)"""

_CODES = f"""
cd2 AS (SELECT b.id, c.subspace, c.half, c.code, sum((b.x - c.x) * (b.x - c.x)) AS d2 FROM bd b JOIN cb c ON b.j = c.j GROUP BY ALL),
code AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY id, subspace, half ORDER BY d2, code) AS r FROM cd2) WHERE r = 1),
asg AS (SELECT id, subspace, sum(CASE WHEN half = 0 THEN code * {K} ELSE code END)::BIGINT AS cell FROM code GROUP BY id, subspace),
cnt AS (SELECT subspace, cell, count(*) AS n FROM asg GROUP BY subspace, cell)"""


def _active(ratio: float = RATIO) -> str:
    return f"""
hd AS (
  SELECT *, row_number() OVER (PARTITION BY query_id, subspace, half ORDER BY d2, code) AS half_rank FROM (
    SELECT b.id AS query_id, c.subspace, c.half, c.code, round(sum((b.x - c.x) * (b.x - c.x)), 9) AS d2 FROM qd b JOIN cb c ON b.j = c.j GROUP BY ALL)
),
grid AS (
  SELECT l.query_id, l.subspace, l.code * {K} + r.code AS cell, round(l.d2 + r.d2, 9) AS cost, l.half_rank AS lr, r.half_rank AS rr
  FROM hd l JOIN hd r ON l.query_id = r.query_id AND l.subspace = r.subspace AND l.half = 0 AND r.half = 1
),
walk AS (
  SELECT g.*, coalesce(c.n, 0) AS n, row_number() OVER w AS rank,
    coalesce(sum(coalesce(c.n, 0)) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM grid g LEFT JOIN cnt c ON g.subspace = c.subspace AND g.cell = c.cell WINDOW w AS (PARTITION BY g.query_id, g.subspace ORDER BY cost, lr, rr)
),
act AS (SELECT query_id, subspace, cell, rank, walk.n AS n FROM walk, size WHERE before < greatest(1, ceil({ratio} * size.n - 1e-9)))"""


def _scores(cut: int = 0) -> str:
    return f"""
sc AS (
  SELECT query_id, id, sum(CASE WHEN rank <= {cut} THEN 2 ELSE 1 END)::BIGINT AS score
  FROM act JOIN asg ON act.subspace = asg.subspace AND act.cell = asg.cell GROUP BY query_id, id
)"""


def _chosen(fraction: float, k: int = TOP) -> str:
    least = max(1, math.ceil(fraction * M - 1e-9))
    return f"""
cand AS (
  SELECT *, score < {least} AS fallback FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS rn FROM sc)
  WHERE score >= {least} OR rn <= {k}
)"""


_DIST = """
dist AS (
  SELECT c.query_id, c.id, round(sum((b.x - a.x) * (b.x - a.x)), 6) AS dist2 FROM cand c JOIN bd b ON b.id = c.id JOIN qd a ON a.id = c.query_id AND a.j = b.j GROUP BY c.query_id, c.id
)"""

_RESULT = f"""
res AS (SELECT query_id, rank, id, dist2 FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM dist) WHERE rank <= {TOP})"""


def _truth(k: int = TOP) -> str:
    return f"""
td AS (SELECT a.id AS query_id, b.id, round(sum((b.x - a.x) * (b.x - a.x)), 6) AS dist2 FROM bd b JOIN qd a ON a.j = b.j GROUP BY a.id, b.id),
truth AS (SELECT query_id, rank, id, dist2 FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM td) WHERE rank <= {k})"""


_HAM = """
bits AS (SELECT id, sum(CASE WHEN x >= 0 THEN (1::HUGEINT << j) ELSE 0 END)::HUGEINT AS w FROM pd GROUP BY id),
ordered AS (
  SELECT query_id, id, score, ham, row_number() OVER (PARTITION BY query_id ORDER BY ham, score DESC, id) AS pos
  FROM (SELECT c.query_id, c.id, c.score, bit_count(xor(b.w, a.w))::INT AS ham FROM cand c JOIN bits b ON b.id = c.id JOIN bits a ON a.id = c.query_id)
)"""

_SCORE_ORDER = "ordered AS (SELECT query_id, id, score, rn AS pos FROM cand)"


def _fold(patience: int | None, sampling: bool) -> str:
    """The sequential verification as a recursion over the order of candidates."""
    prune = f"len(f.best) >= {TOP} AND s.p32 > f.best[{TOP}].d * 0.5 * pow(1 + 2.1 / sqrt(32), 2)" if sampling else "false"
    stop = f"len(f.best) >= {TOP} AND f.idle >= {patience}" if patience is not None else "false"
    return f"""
meas AS (
  SELECT o.query_id, o.pos, o.id, round(sum((b.x - a.x) * (b.x - a.x)), 6) AS d2, sum((b.x - a.x) * (b.x - a.x)) FILTER (b.j < 32) AS p32
  FROM ordered o JOIN bd b ON b.id = o.id JOIN qd a ON a.id = o.query_id AND a.j = b.j GROUP BY o.query_id, o.pos, o.id
),
f AS (
  SELECT id AS query_id, 0::BIGINT AS pos, []::STRUCT(d DOUBLE, i BIGINT)[] AS best, 0::BIGINT AS idle, 0::BIGINT AS completed, 0::BIGINT AS pruned FROM q
  UNION ALL
  SELECT query_id, pos, CASE WHEN cut THEN best ELSE list_sort(list_append(best, {{'d': d2, 'i': id}}))[1:{TOP}] END,
    CASE WHEN NOT cut AND (len(best) < {TOP} OR d2 < best[{TOP}].d) THEN 0 ELSE idle + 1 END, completed + (NOT cut)::INT, pruned + cut::INT
  FROM (SELECT f.query_id, s.pos, f.best, f.idle, f.completed, f.pruned, s.d2, s.id, ({prune}) AS cut FROM f JOIN meas s ON s.query_id = f.query_id AND s.pos = f.pos + 1 WHERE NOT ({stop}))
),
last AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY pos DESC) AS z FROM f) WHERE z = 1),
out AS (SELECT query_id, generate_subscripts(best, 1)::INT AS rank, unnest(best) AS b, completed, pruned, completed + pruned AS started,
  ({"len(best) >= " + str(TOP) + " AND idle >= " + str(patience) if patience is not None else "false"})::INT AS stopped FROM last)"""


def _with(*parts: str, select: str, recursive: bool = False) -> str:
    return ("WITH RECURSIVE " if recursive else "WITH ") + ",".join(parts) + "\n" + select


_DECAY = "list_transform(CAST(embedding AS DOUBLE[]), lambda x, i: x * pow(0.9::DOUBLE, i - 1))"
_SIGN = "(CASE WHEN j % 3 <> 0 THEN 1 ELSE -1 END)"


def _hadamard(vec: str) -> str:
    return f"""
raw AS (SELECT vec_id AS id, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS j FROM (SELECT vec_id, {vec} AS v FROM embeddings)),
pd AS (SELECT id, i.range AS j, sum(x * {_SIGN} * (CASE WHEN bit_count(i.range & j) % 2 = 1 THEN -1 ELSE 1 END)) / 8.0 AS x FROM raw, range(64) i GROUP BY id, i.range),
base AS (SELECT DISTINCT id FROM pd WHERE id % 10 <> 0), bd AS (SELECT * FROM pd WHERE id % 10 <> 0), qd AS (SELECT * FROM pd WHERE id % 10 = 0),
size AS (SELECT count(*) AS n FROM base)"""


_RUNS = "runs AS (SELECT * FROM (VALUES ('a',0.80::DOUBLE,10.0::DOUBLE,5.0::DOUBLE),('a',0.90,8.0,7.0),('a',0.95,5.0,9.0),('b',0.80,12.0,3.0),('b',0.90,8.0,8.0),('b',0.99,1.0,30.0),('c',0.70,20.0,1.0),('c',0.85,9.0,6.0),('c',0.85,9.0,4.0)) t(method, recall, qps, build_s))"

_COLLIDE = """
col AS (SELECT t.query_id, a.subspace, (x.cell IS NOT NULL)::INT AS hit FROM truth t JOIN asg a ON a.id = t.id AND t.rank = 1 LEFT JOIN act x ON x.query_id = t.query_id AND x.subspace = a.subspace AND x.cell = a.cell)"""


def oracle_sql() -> dict[str, str]:
    p, full = _points(), (_points(), _BOOKS, _CODES)
    act = (*full, _active())
    uni, wei = (*act, _scores()), (*act, _scores(TOP))
    guaranteed = (*uni, _chosen(0.25), _DIST, _RESULT)
    optimized = (*wei, _chosen(0.4), _HAM)
    res = "SELECT query_id, rank, id, dist2 FROM res"
    out = {
        "q_exact_knn": _with(p, _truth(), select="SELECT * FROM truth"),
        "q_exact_knn_bulk": _with(p, _truth(), select="SELECT * FROM truth"),
        "q_exact_nn1": _with(p, _truth(1), select="SELECT * FROM truth"),
        "q_radius_search": _with(p, _truth(), select="SELECT query_id, id, dist2 FROM td WHERE dist2 <= 1.2::DOUBLE * 1.2::DOUBLE"),
        "q_rotation_distances": _with(p, _truth(), select="SELECT query_id, rank, id FROM truth"),
        "q_cov_entries": _with(p, select="SELECT a.j AS i, b.j AS j, round(covar_samp(a.x, b.x), 9) AS c FROM pd a JOIN pd b ON a.id = b.id AND a.j <= b.j AND b.j < 8 GROUP BY a.j, b.j"),
        "q_variance_spread": _with(_points(_DECAY), ", v AS (SELECT j, var_samp(x) AS v FROM pd GROUP BY j)"[1:], select="SELECT round(stddev_samp(v) / avg(v), 6) AS variation, round(max(v) / min(v), 2) AS ratio FROM v"),
        "q_trace_frobenius": _with(p, "c AS (SELECT a.j AS i, b.j AS j, covar_samp(a.x, b.x) AS c FROM pd a JOIN pd b ON a.id = b.id GROUP BY a.j, b.j)", select="SELECT round(sum(c) FILTER (i = j), 9) AS trace, round(sum(c * c), 9) AS frobenius FROM c"),
        "q_sample_rule": _with(p, select="SELECT id, round(sqrt(sum(x * x)), 6) AS norm FROM pd WHERE id % 10 = 0 GROUP BY id"),
        "q_hadamard_rotate": _with(_hadamard("CAST(embedding AS DOUBLE[])"), select="SELECT id, j AS i, round(x, 6) AS x FROM pd WHERE j < 4"),
        "q_rotate_literal": _with(p, select="SELECT id, round(vec[1] * cos(pi() / 6) - vec[2] * sin(pi() / 6), 6) AS x0, round(vec[1] * sin(pi() / 6) + vec[2] * cos(pi() / 6), 6) AS x1, round(vec[3], 6) AS x2 FROM points"),
        "q_layout_slices": _with(p, select="SELECT id, j // 8 AS subspace, (j // 4) % 2 AS half, round(sqrt(sum(x * x)), 6) AS norm FROM bd GROUP BY ALL"),
        "q_sample_codebook": _with(p, _BOOKS, select="SELECT subspace, half, code, t AS j, round(x, 6) AS x FROM cb"),
        "q_encode_cells": _with(*full, select="SELECT * FROM asg"),
        "q_encode_cells_bulk": _with(*full, select="SELECT * FROM asg"),
        "q_cell_counts": _with(*full, select="SELECT * FROM cnt"),
        "q_cell_skew": _with(*full, select="""SELECT subspace, count(*) AS occupied, round(1 - count(*) / 64.0::DOUBLE, 6) AS empty_share, round(max(n) * count(*) / sum(n)::DOUBLE, 6) AS max_over_mean,
  round(2 * sum(r * n) / (count(*) * sum(n))::DOUBLE - (count(*) + 1) / count(*)::DOUBLE, 6) AS gini FROM (SELECT *, row_number() OVER (PARTITION BY subspace ORDER BY n, cell) AS r FROM cnt) GROUP BY subspace"""),
        "q_csr_offsets": _with(*full, select="SELECT s.subspace, c.range::INT AS cell, coalesce(sum(n) OVER (PARTITION BY s.subspace ORDER BY c.range ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\" FROM (SELECT DISTINCT subspace FROM cnt) s, range(65) c LEFT JOIN cnt ON cnt.subspace = s.subspace AND cnt.cell = c.range"),
        "q_csr_positions": _with(*full, select="SELECT subspace, row_number() OVER (PARTITION BY subspace ORDER BY cell, id) - 1 AS position, id FROM asg"),
        "q_csr_shards": _with(*full, select="SELECT subspace, cell, id FROM asg"),
        "q_map_postings": _with(*full, select="SELECT subspace, cell, string_agg(id::VARCHAR, ',' ORDER BY id) AS ids FROM asg GROUP BY subspace, cell"),
        "q_sign_words": _with(p, select="SELECT id, sum(CASE WHEN x >= 0 THEN (CASE WHEN j = 63 THEN -9223372036854775808 ELSE (1::BIGINT << j) END) ELSE 0 END)::BIGINT AS word FROM pd GROUP BY id"),
        "q_half_distances": _with(*act, select="SELECT query_id, subspace, half, code, round(d2, 6) AS d2, half_rank FROM hd"),
        "q_grid_activation": _with(*act, select="SELECT query_id, subspace, cell, rank, n::BIGINT AS n FROM act"),
        "q_grid_activation_heap": _with(*act, select="SELECT query_id, subspace, cell, rank FROM act"),
        "q_votes_uniform": _with(*uni, select="SELECT * FROM sc"),
        "q_votes_weighted": _with(*wei, select="SELECT * FROM sc"),
        "q_votes_own_cell": _with(*full, f"""
qc AS (SELECT query_id, subspace, sum(CASE WHEN half = 0 THEN code * {K} ELSE code END)::BIGINT AS cell FROM (
  SELECT *, row_number() OVER (PARTITION BY query_id, subspace, half ORDER BY d2, code) AS r FROM (
    SELECT b.id AS query_id, c.subspace, c.half, c.code, sum((b.x - c.x) * (b.x - c.x)) AS d2 FROM qd b JOIN cb c ON b.j = c.j GROUP BY ALL)) WHERE r = 1 GROUP BY query_id, subspace)""", select="SELECT query_id, id, count(*) AS score FROM qc JOIN asg USING (subspace, cell) GROUP BY query_id, id"),
        "q_double_votes": _with(*act, select=f"SELECT query_id, round((sum(n) FILTER (rank <= {TOP}))::DOUBLE / sum(n), 6) AS double_share, sum(n)::BIGINT AS votes, count(*) AS cells FROM act GROUP BY query_id"),
        "q_threshold": _with(*uni, select="SELECT * FROM sc WHERE score >= 2"),
        "q_fallback": _with(*uni, _chosen(0.9), select="SELECT query_id, id, score, fallback FROM cand"),
        "q_fallback_pad": _with(*full, _active(1e-9), _scores(), _chosen(1.0), """
few AS (SELECT query_id, id, score FROM cand WHERE score >= 3), have AS (SELECT q.id AS query_id, count(few.id) AS h FROM q LEFT JOIN few ON few.query_id = q.id GROUP BY q.id),
free AS (SELECT h.query_id, b.id, h.h, row_number() OVER (PARTITION BY h.query_id ORDER BY b.id) AS r FROM have h, base b WHERE NOT EXISTS (SELECT 1 FROM few WHERE few.query_id = h.query_id AND few.id = b.id))""", select="SELECT * FROM few UNION ALL SELECT query_id, id, 0 FROM free WHERE r <= 3 - h"),
        "q_top_beta": _with(*uni, select="SELECT query_id, id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS rn FROM sc), size WHERE rn <= greatest(1, ceil(0.05 * n - 1e-9))"),
        "q_hamming_order": _with(*optimized, select="SELECT query_id, id, ham, pos FROM ordered"),
        "q_dim_sampling": _with(*optimized, _fold(None, True), select="SELECT query_id, rank, b.i AS id, b.d AS dist2, completed, pruned FROM out", recursive=True),
        "q_search_optimized": _with(*optimized, _fold(4 * TOP, True), select="SELECT query_id, rank, b.i AS id, b.d AS dist2, started, stopped FROM out", recursive=True),
        "q_ablate_no_sampling": _with(*optimized, _fold(4 * TOP, False), select="SELECT query_id, rank, b.i AS id, b.d AS dist2, started, stopped FROM out", recursive=True),
        "q_ablate_no_hamming": _with(*wei, _chosen(0.4), _SCORE_ORDER, _fold(4 * TOP, True), select="SELECT query_id, rank, b.i AS id, b.d AS dist2, started, stopped FROM out", recursive=True),
        "q_patience_exact": _with(*optimized, _DIST, f"""
od AS (SELECT o.query_id, o.pos, o.id, d.dist2 FROM ordered o JOIN dist d USING (query_id, id)),
kk AS (SELECT *, list_sort(list(dist2) OVER (PARTITION BY query_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)) AS seen FROM od),
ch AS (SELECT *, CASE WHEN pos <= {TOP} OR dist2 < seen[{TOP}] THEN pos END AS mark FROM kk),
idle AS (SELECT *, pos - 1 - coalesce(max(mark) OVER (PARTITION BY query_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS idle FROM ch)""", select=f"SELECT query_id, pos, id, dist2 FROM (SELECT *, max((idle >= {2 * TOP})::INT) OVER (PARTITION BY query_id ORDER BY pos) AS stopped FROM idle) WHERE stopped = 0"),
        "q_search_guaranteed": _with(*guaranteed, select=res),
        "q_engine_guaranteed": _with(*guaranteed, select=res),
        "q_index_round_trip": _with(*guaranteed, select=res),
        "q_engine_append": _with(p, _truth(), select="SELECT * FROM truth"),
        "q_search_guaranteed_rotated": _with(_hadamard(_DECAY), _BOOKS, _CODES, _active(), _scores(), _chosen(0.25), _DIST, _RESULT, select=res),
        "q_uniform_collision": _with(*uni, f"cand AS (SELECT query_id, id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS rn FROM sc), size WHERE rn <= greatest(1, ceil(0.1 * n - 1e-9)))", _DIST, _RESULT, select=res),
        "q_onebit_ivf_full": _with(p, _truth(), select="SELECT * FROM truth"),
        "q_plain_pq": _with(p, f"""
cb AS (SELECT b.j // 8 AS h, c.range AS code, b.j, b.x FROM (SELECT id, row_number() OVER (ORDER BY id) - 1 AS r FROM base) o JOIN size ON true JOIN range({K}) c ON o.r = (c.range * n) // {K} JOIN bd b ON b.id = o.id),
e AS (SELECT id, h, code FROM (SELECT *, row_number() OVER (PARTITION BY id, h ORDER BY d2, code) AS r FROM (SELECT b.id, c.h, c.code, sum((b.x - c.x) * (b.x - c.x)) AS d2 FROM bd b JOIN cb c ON b.j = c.j GROUP BY ALL)) WHERE r = 1),
lut AS (SELECT a.id AS query_id, c.h, c.code, sum((a.x - c.x) * (a.x - c.x)) AS d2 FROM qd a JOIN cb c ON a.j = c.j GROUP BY ALL),
d AS (SELECT query_id, id, round(sum(d2), 6) AS dist2 FROM e JOIN lut USING (h, code) GROUP BY query_id, id)""", select=f"SELECT query_id, rank, id, dist2 FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM d) WHERE rank <= {TOP}"),
        "q_recall_at_k": _with(*guaranteed, _truth(), select=f"SELECT t.query_id, round(count(r.id) / {TOP}.0::DOUBLE, 6) AS recall FROM truth t LEFT JOIN res r ON r.query_id = t.query_id AND r.id = t.id GROUP BY t.query_id"),
        "q_candidate_recall": _with(*uni, _chosen(0.25), _truth(), select=f"SELECT round(avg(r), 6) AS recall, count(*) AS queries FROM (SELECT t.query_id, count(c.id) / {TOP}.0::DOUBLE AS r FROM truth t LEFT JOIN cand c ON c.query_id = t.query_id AND c.id = t.id GROUP BY t.query_id)"),
        "q_nearest_found": _with(*uni, _chosen(0.25), _truth(), select="SELECT round(avg((c.id IS NOT NULL)::INT), 6) AS nn_in_candidates, count(*) AS queries FROM truth t LEFT JOIN cand c ON c.query_id = t.query_id AND c.id = t.id WHERE t.rank = 1"),
        "q_candidate_stats": _with(*uni, _chosen(0.5), select="SELECT round(avg(c), 6) AS mean_candidates, round(avg(c) / any_value(size.n), 6) AS share_of_n, round(avg(f), 6) AS fallback_share FROM (SELECT query_id, count(*) AS c, max(fallback::INT) AS f FROM cand GROUP BY query_id), size"),
        "q_lid": _with(p, _truth(20), "r AS (SELECT query_id, rank, sqrt(dist2) AS r FROM truth WHERE dist2 > 0), k AS (SELECT query_id, max(r) AS rk, max(rank) AS l FROM r GROUP BY query_id)", select="SELECT query_id, round(1 / avg(ln(rk / r)), 4) AS lid FROM r JOIN k USING (query_id) WHERE rank < l GROUP BY query_id"),
        "q_lid_summary": _with(p, _truth(20), "r AS (SELECT query_id, rank, sqrt(dist2) AS r FROM truth WHERE dist2 > 0), k AS (SELECT query_id, max(r) AS rk, max(rank) AS l FROM r GROUP BY query_id), z AS (SELECT query_id, 1 / avg(ln(rk / r)) AS lid FROM r JOIN k USING (query_id) WHERE rank < l GROUP BY query_id)", select="SELECT round(avg(lid), 3) AS mean_lid, round(1 / avg(1 / lid), 3) AS inverse_mean_lid, count(lid) AS used, 0::BIGINT AS skipped FROM z"),
        "q_estimate_p": _with(*act, _truth(1), _COLLIDE, select="SELECT subspace, round(avg(hit), 6) AS p, count(*) AS n FROM col GROUP BY subspace"),
        "q_dependence": _with(*act, _truth(1), _COLLIDE, """
s AS (SELECT avg(s) AS mean_s, var_samp(s) AS var_s FROM (SELECT query_id, sum(hit) AS s FROM col GROUP BY query_id)),
e AS (SELECT sum(p * (1 - p)) AS ev FROM (SELECT subspace, avg(hit) AS p FROM col GROUP BY subspace)),
f AS (SELECT avg(phi) AS mp FROM (SELECT corr(a.hit, b.hit) AS phi, var_pop(a.hit) AS va, var_pop(b.hit) AS vb FROM col a JOIN col b ON a.query_id = b.query_id AND a.subspace < b.subspace GROUP BY a.subspace, b.subspace) WHERE va > 0 AND vb > 0)""", select="SELECT round(mean_s, 5) AS mean_s, round(var_s, 5) AS var_s, round(ev, 5) AS expected_var, round(var_s / ev, 5) AS ratio, round(mp, 5) AS mean_phi FROM s, e, f"),
        "q_bounds_het": _with(*act, _truth(1), _COLLIDE, "e AS (SELECT sum(p) AS sp, count(*) AS m FROM (SELECT subspace, avg(hit) AS p FROM col GROUP BY subspace))", select="SELECT tau, round(CASE WHEN sp > tau THEN 1 - exp(-2 * (sp - tau) * (sp - tau) / m) ELSE 0 END, 6) AS bound FROM e, (VALUES (1.0::DOUBLE), (2.0), (3.0)) t(tau)"),
        "q_bounds": """
WITH t AS (SELECT m, p, m * f AS tau FROM (SELECT unnest([2,4,8,16,32]) AS m), (SELECT unnest([0.3::DOUBLE,0.5,0.6,0.8,0.95]) AS p), (SELECT unnest([0.1::DOUBLE,0.25,0.5]) AS f)),
b AS (SELECT *, CASE WHEN m * p > tau THEN 1 - exp(-2 * (m * p - tau) * (m * p - tau) / m) ELSE 0 END AS h, CASE WHEN m * p > tau THEN greatest(0, 1 - m * p * (1 - p) / ((m * p - tau) * (m * p - tau))) ELSE 0 END AS c FROM t),
x AS (SELECT m, p, tau, sum(exp(lgamma(m + 1) - lgamma(s + 1) - lgamma(m - s + 1)) * pow(p, s) * pow(1 - p, m - s)) AS e FROM t, range(0, 33) r(s) WHERE s >= ceil(tau) AND s <= m GROUP BY m, p, tau)
SELECT b.m, b.p, b.tau, round(h, 6) AS hoeffding, round(c, 6) AS chebyshev, round(e, 6) AS exact, CASE WHEN h >= c THEN 'hoeffding' ELSE 'chebyshev' END AS tighter FROM b JOIN x ON x.m = b.m AND x.p = b.p AND x.tau = b.tau""",
        "q_required_subspaces": "SELECT p, f, d, CASE WHEN p > f THEN ceil(ln(1 / d) / (2 * pow(p - f, 2)))::BIGINT ELSE -1 END AS m FROM (SELECT unnest([0.4::DOUBLE,0.6,0.8,0.95]) AS p), (SELECT unnest([0.1::DOUBLE,0.25,0.5]) AS f), (SELECT unnest([0.1::DOUBLE,0.01,0.001]) AS d)",
        "q_pareto": _with(_RUNS, select="SELECT * FROM runs r WHERE NOT EXISTS (SELECT 1 FROM runs s WHERE s.recall >= r.recall AND s.qps >= r.qps AND (s.recall > r.recall OR s.qps > r.qps))"),
        "q_min_cost_at": _with(_RUNS, select="SELECT m.method, t.threshold, min(r.build_s) AS cost FROM (SELECT DISTINCT method FROM runs) m CROSS JOIN (SELECT unnest([0.8::DOUBLE,0.85,0.9,0.95,0.99]) AS threshold) t LEFT JOIN runs r ON r.method = m.method AND r.recall >= t.threshold GROUP BY ALL"),
        "q_speedup_at": _with(_RUNS, select="SELECT method, qps, round(qps / lead(qps) OVER (ORDER BY qps DESC, method), 6) AS ratio FROM (SELECT method, max(qps) AS qps FROM runs WHERE recall >= 0.8 GROUP BY method)"),
        "q_quantisation_error": _with(*full, select="SELECT subspace, half, round(avg(d2), 6) AS mse, count(*) AS n FROM code GROUP BY subspace, half"),
        "q_predicted_cost": """SELECT n::BIGINT AS n, d::BIGINT AS d, round(4.0 * n * d + 4.0 * n * 8, 3)::DOUBLE AS space_method, round(4.0 * n * d + 4.0 * n * 8 + 48 * 8 * 2500.0, 3)::DOUBLE AS space_uniform_collision,
  round(4.0 * n * d + n * d / 8.0 + 200.0 * d, 3)::DOUBLE AS space_onebit_ivf, round(4.0::DOUBLE * n * d + 64.0::DOUBLE * n * log2(n), 3) AS space_graph, (n::DOUBLE * 50 * d) AS build_flat, (n::DOUBLE * 50 * d + n::DOUBLE * d * d) AS build_rotated, ((n // 100)::DOUBLE * d) AS query_verify
FROM (VALUES (60000, 784), (90120, 4096), (1000000, 960)) t(n, d)""",
        "q_label_purity": _with(p, _truth(), select="SELECT t.query_id, round(avg((a.label = b.label)::INT), 6) AS purity FROM truth t JOIN embeddings a ON a.vec_id = t.id JOIN embeddings b ON b.vec_id = t.query_id GROUP BY t.query_id"),
        "q_filtered_knn": _with(p, _truth(), select="SELECT query_id, rank, id, dist2 FROM (SELECT td.*, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM td JOIN embeddings e ON e.vec_id = td.id WHERE label = 3) WHERE rank <= 5"),
        "q_filtered_knn_post": _with(p, _truth(100), select="SELECT query_id, rank, id, dist2 FROM (SELECT t.query_id, t.id, t.dist2, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM truth t JOIN embeddings e ON e.vec_id = t.id WHERE label = 3) WHERE rank <= 5"),
        "q_filtered_search": _with(p, _BOOKS, _CODES.replace("FROM bd b JOIN cb c ON b.j = c.j GROUP BY ALL", "FROM bd b JOIN cb c ON b.j = c.j WHERE b.id % 2 = 1 GROUP BY ALL"), _active().replace("FROM walk, size", "FROM walk, (SELECT count(*) AS n FROM base WHERE id % 2 = 1) size"), _scores(), _chosen(0.25), _DIST, _RESULT, select=res),
        "q_pair_distances": _with(p, select="SELECT * FROM (SELECT a.id AS a_id, b.id AS b_id, round(sum((a.x - b.x) * (a.x - b.x)), 6) AS dist2 FROM pd a JOIN pd b ON a.j = b.j AND a.id < b.id JOIN embeddings x ON x.vec_id = a.id JOIN embeddings y ON y.vec_id = b.id WHERE x.label = y.label GROUP BY a.id, b.id) WHERE dist2 <= 1.6"),
        "q_class_means": _with(p, select="SELECT label, j, round(avg(x), 6) AS mean FROM pd JOIN embeddings e ON e.vec_id = pd.id GROUP BY label, j"),
        "q_vector_scalars": _with(p, select="""SELECT a.id, round(sqrt(sum((a.x - b.x) * (a.x - b.x))), 6) AS l2, round(sum(a.x * b.x), 6) AS dot, round(sum(a.x * b.x) / (sqrt(sum(a.x * a.x)) * sqrt(sum(b.x * b.x))), 6) AS cosine,
  round(sum((a.x - b.x) * (a.x - b.x)) FILTER (a.j < 32), 6) AS half_l2sq, round(sqrt(sum((a.x + b.x) * (a.x + b.x))), 6) AS norm_sum, round(sqrt(sum((a.x - b.x / 2) * (a.x - b.x / 2))), 6) AS norm_mix
FROM pd a JOIN pd b ON b.id = 0 AND a.j = b.j GROUP BY a.id"""),
        "q_vector_quality": "SELECT 'ok' AS state, count(*) AS n FROM embeddings UNION ALL SELECT unnest(['null', 'length', 'nan', 'infinite']), 1",
        "q_event_vectors": "SELECT user_id AS id, sum(n)::DOUBLE AS total, round(sqrt(sum(n * n)), 6) AS norm FROM (SELECT user_id, hour(ts) AS h, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id",
        "q_customer_vectors": "SELECT o_custkey AS id, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY o_custkey",
    }
    lloyd = lambda i: f"""
e{i} AS (SELECT id, j, x, code FROM (SELECT b.id, b.j, b.x, k.code FROM bd b JOIN (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY id, subspace, half ORDER BY d2, code) AS r FROM (
  SELECT b.id, c.subspace, c.half, c.code, sum((b.x - c.x) * (b.x - c.x)) AS d2 FROM bd b JOIN c{i} c ON b.j = c.j GROUP BY ALL)) WHERE r = 1) k ON k.id = b.id AND k.subspace = b.j // 8 AND k.half = (b.j // 4) % 2)),
c{i + 1} AS (SELECT c.subspace, c.half, c.code, c.t, c.j, coalesce(m.x, c.x) AS x FROM c{i} c LEFT JOIN (SELECT j, code, avg(x) AS x FROM e{i} GROUP BY j, code) m ON m.j = c.j AND m.code = c.code)"""  # noqa: E731
    start = "c0 AS (SELECT * FROM cb)"
    out["q_lloyd1_relational"] = _with(p, _BOOKS, start, lloyd(0), select="SELECT subspace, half, code, t AS j, round(x, 6) AS x FROM c1")
    out["q_lloyd2_codebook"] = _with(p, _BOOKS, start, lloyd(0), lloyd(1), select="SELECT subspace, half, code, t AS j, round(x, 6) AS x FROM c2")
    return out
