"""The queries in DuckDB SQL, by definition: train by recursion, score everything."""

from __future__ import annotations

ENT = """ent AS (SELECT CAST('0x' || substr(md5(concat_ws('-', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(round(l_extendedprice * 100) AS BIGINT))), 1, 15) AS BIGINT) AS id,
  l_quantity / 50e0 AS f0, l_extendedprice / 105000e0 AS f1, l_discount / 1e-1 AS f2, l_tax / 8e-2 AS f3,
  CASE WHEN l_extendedprice >= 1500 * l_quantity THEN 1 ELSE -1 END AS y, l_returnflag, l_linestatus, l_orderkey FROM lineitem)"""
EX = "ex AS (SELECT *, row_number() OVER (ORDER BY id) AS k FROM ent ORDER BY id LIMIT 200)"
DIM = range(4)
W, Fs = [f"w{k}" for k in DIM], [f"f{k}" for k in DIM]


def dot(w: str = "", f: str = "") -> str:
    total = "0e0"
    for k in DIM:
        total = f"({total} + {w}w{k} * {f}f{k})"
    return total


SLOPES = {"hinge": "CASE WHEN y * z < 1 THEN -CAST(y AS DOUBLE) ELSE 0e0 END", "logistic": "-y / (1e0 + exp(y * z))", "squared": "z - y"}


def trail(loss: str = "hinge", eta: str = "2e0", l2: str = "1e-2", name: str = "trail", examples: str = "ex", label: str = "y") -> str:
    """Models t = 0, 1, … by one recursive step for each example."""
    inner = f"SELECT m.t AS t0, {', '.join('m.' + w for w in W)}, m.b, {', '.join('e.' + f for f in Fs)}, e.{label} AS y, {eta} / (1e0 + {l2} * {eta} * m.t) AS eta, {dot('m.', 'e.')} - m.b AS z FROM {name} m JOIN {examples} e ON e.k = m.t + 1"
    step = ", ".join(f"w{k} * (1e0 - eta * {l2}) - eta * g * f{k}" for k in DIM)
    return f"{name} AS (SELECT 0 AS t, {', '.join('0e0 AS ' + w for w in W)}, 0e0 AS b UNION ALL SELECT t0 + 1, {step}, b + eta * g FROM (SELECT *, {SLOPES[loss]} AS g FROM ({inner})))"


MODELS = f"m AS (SELECT t - 160 AS j, {', '.join(W)}, b FROM trail WHERE t >= 160)"
LARGEST = "mx AS (SELECT max(sqrt(f0 * f0 + f1 * f1 + f2 * f2 + f3 * f3)) AS largest FROM ent)"
DEVIATIONS = (
    "dv AS (SELECT s.j AS s, i.j AS i, (i.b - s.b) - largest * sqrt((i.w0 - s.w0) * (i.w0 - s.w0) + (i.w1 - s.w1) * (i.w1 - s.w1) + (i.w2 - s.w2) * (i.w2 - s.w2) + (i.w3 - s.w3) * (i.w3 - s.w3)) AS low,"
    " (i.b - s.b) + largest * sqrt((i.w0 - s.w0) * (i.w0 - s.w0) + (i.w1 - s.w1) * (i.w1 - s.w1) + (i.w2 - s.w2) * (i.w2 - s.w2) + (i.w3 - s.w3) * (i.w3 - s.w3)) AS high FROM m s JOIN m i ON i.j >= s.j CROSS JOIN mx),"
    " wm AS (SELECT *, min(low) OVER (PARTITION BY s ORDER BY i) AS lw, max(high) OVER (PARTITION BY s ORDER BY i) AS hw FROM dv)"
)
HEAD = f"WITH RECURSIVE {ENT}, {EX}, {trail()}, {MODELS}"
BANDS = f"{HEAD}, {LARGEST}, {DEVIATIONS}"
LAST = f"{HEAD}, fin AS (SELECT ent.*, {dot('m.', 'ent.')} - m.b AS eps FROM ent, m WHERE m.j = 40), v AS (SELECT *, CASE WHEN eps >= 0 THEN 1 ELSE -1 END AS class FROM fin)"
FINAL = f"{LAST} SELECT id, class FROM v"
MARGINS = f"ms AS (SELECT m.j AS s, ent.id, {dot('m.', 'ent.')} - m.b AS eps FROM ent, m)"
FAMILY = "fam AS (SELECT wm.s, wm.i, count(ms.id) FILTER (WHERE ms.eps >= wm.lw AND ms.eps < wm.hw) AS n, count(ms.id) FILTER (WHERE ms.eps >= wm.lw) AS above FROM wm JOIN ms ON ms.s = wm.s GROUP BY wm.s, wm.i)"
POSITIVE = "pos AS (SELECT s AS i, count(*) FILTER (WHERE eps >= 0) AS n_pos FROM ms GROUP BY s)"
SIZE = "nn AS (SELECT count(*) / 25e-2 AS whole FROM ent)"


def ledger(cost: str) -> str:
    return (
        f"{BANDS}, {MARGINS}, {FAMILY}, {POSITIVE}, {SIZE}, led AS (SELECT 0 AS i, 0 AS s, 0e0 AS waste, 0e0 AS cost, FALSE AS reclustered UNION ALL "
        "SELECT l.i + 1, CASE WHEN l.waste >= whole THEN l.i + 1 ELSE l.s END, CASE WHEN l.waste >= whole THEN 0e0 ELSE l.waste + c END, CASE WHEN l.waste >= whole THEN whole ELSE c END, l.waste >= whole"
        f" FROM (SELECT led.*, whole, {cost} AS c FROM led, nn, fam f, pos p WHERE f.s = led.s AND f.i = led.i + 1 AND p.i = led.i + 1) l)"
        " SELECT led.i AS round, led.s, CASE WHEN reclustered THEN 0e0 ELSE round(wm.lw, 6) END AS lw, CASE WHEN reclustered THEN 0e0 ELSE round(wm.hw, 6) END AS hw, CASE WHEN reclustered THEN 0 ELSE fam.n END AS n_band, round(cost, 6) AS cost, round(waste, 6) AS waste, reclustered"
        " FROM led JOIN wm ON wm.s = led.s AND wm.i = led.i JOIN fam ON fam.s = led.s AND fam.i = led.i WHERE led.i > 0"
    )


TERMS = r"t AS (SELECT {key} AS id, unnest({slice}) AS term FROM (SELECT {key}, list_filter(regexp_split_to_array(lower(coalesce({text}, '')), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '') AS ts FROM {table})), c AS (SELECT id, term, CAST(count(*) AS DOUBLE) AS val FROM t GROUP BY id, term)"


def terms(table: str = "documents", key: str = "doc_id", text: str = "text", first: int | None = None) -> str:
    return TERMS.format(table=table, key=key, text=text, slice=f"ts[1:{first}]" if first else "ts")


def _flags() -> str:
    """Models of one class against the rest, and each entity's scores."""
    examples = ", ".join(f"CASE WHEN l_returnflag = '{c}' THEN 1 ELSE -1 END AS y_{c}" for c in "ANR")
    parts = [f"exf AS (SELECT *, {examples} FROM ex)"]
    parts += [trail(name=f"tr_{c}", examples="exf", label=f"y_{c}") for c in "ANR"]
    scores = ", ".join(f"{dot(f'{c}.', 'ent.')} - {c}.b AS s_{c}" for c in "ANR")
    joins = ", ".join(f"(SELECT * FROM tr_{c} WHERE t = 200) {c}" for c in "ANR")
    return f"WITH RECURSIVE {ENT}, {EX}, {', '.join(parts)}, sc AS (SELECT ent.id, ent.l_returnflag, {scores} FROM ent, {joins})"


BEST = "CASE WHEN s_A >= s_N AND s_A >= s_R THEN 'A' WHEN s_N >= s_R THEN 'N' ELSE 'R' END"
ONE = "o AS (SELECT id, f1 AS x, y, CASE WHEN y > 0 THEN 1e0 ELSE 2e0 END AS k FROM ent)"
STATS = "SELECT dataset, n_entities, n_features, round(mean_nonzero, 6) AS mean_nonzero FROM ("


def _events(windows: str) -> str:
    return f"WITH w AS ({windows}) SELECT user_id, start, n, round(total, 4) AS total, CASE WHEN (0e0 + 1e0 * (n / 10e0)) + 1e0 * (total / n / 100e0) - 7e-1 >= 0 THEN 1 ELSE -1 END AS class FROM w"


def _schedules() -> str:
    """Every schedule of ten rounds as the bits of a number."""
    return (
        f"{BANDS}, {MARGINS}, {FAMILY}, {SIZE}, sh AS (SELECT unnest([5e-2, 1e-1, 25e-2, 1e0]) AS share),"
        " sc AS (SELECT CAST(range AS BIGINT) AS bits FROM range(1024)), rd AS (SELECT CAST(range AS BIGINT) AS i FROM range(1, 11)),"
        " lastr AS (SELECT bits, a.i, coalesce(max(b.i) FILTER (WHERE (bits >> (b.i - 1)) & 1 = 1 AND b.i <= a.i), 0) AS s FROM sc, rd a, rd b GROUP BY bits, a.i),"
        " paid AS (SELECT bits, sum(n) AS rows FROM lastr l JOIN fam f ON f.s = l.s AND f.i = l.i GROUP BY bits),"
        " best AS (SELECT share, min(rows + bit_count(bits) * whole * share) AS best FROM paid, nn, sh GROUP BY share),"
        " sim AS (SELECT share, 0 AS i, 0 AS s, 0e0 AS waste, 0e0 AS total FROM sh UNION ALL SELECT share, i + 1, CASE WHEN buy THEN i + 1 ELSE s END, CASE WHEN buy THEN 0e0 ELSE waste + n END, total + CASE WHEN buy THEN whole * share ELSE n END"
        " FROM (SELECT sim.*, f.n, whole, waste >= whole * share AS buy FROM sim, nn, fam f WHERE f.s = sim.s AND f.i = sim.i + 1 AND sim.i < 10))"
        " SELECT best.share, round(best, 6) AS best, round(sim.total, 6) AS rule FROM best JOIN sim ON sim.share = best.share AND sim.i = 10"
    )


def _policies() -> str:
    rules = {"never": "FALSE", "always": "TRUE", "every_10": "(run.i + 1) % 10 = 0", "rent_or_buy": "waste >= whole"}
    buy = " ".join(f"WHEN policy = '{k}' THEN {v}" for k, v in rules.items())
    return (
        f"{BANDS}, {MARGINS}, {FAMILY}, {SIZE}, run AS (SELECT unnest([{', '.join(repr(k) for k in rules)}]) AS policy, 0 AS i, 0 AS s, 0e0 AS waste, 0e0 AS total, 0 AS bought UNION ALL"
        " SELECT policy, i + 1, CASE WHEN buy THEN i + 1 ELSE s END, CASE WHEN buy THEN 0e0 ELSE waste + n END, total + CASE WHEN buy THEN whole ELSE n END, bought + CAST(buy AS INT)"
        f" FROM (SELECT run.*, f.n, whole, CASE {buy} END AS buy FROM run, nn, fam f WHERE f.s = run.s AND f.i = run.i + 1))"
        " SELECT policy, CAST(bought AS BIGINT) AS n_reclusters, round(total, 6) AS total_cost FROM run WHERE i = 40"
    )


def _survivors() -> str:
    kept = "sv AS (SELECT id, f0, f1, f2, f3, CASE WHEN k % 7 = 0 THEN -y ELSE y END AS y, row_number() OVER (ORDER BY k) AS k FROM ex WHERE k % 5 <> 0)"
    return f"WITH RECURSIVE {ENT}, {EX}, {kept}, {trail(examples='sv')}, m AS (SELECT * FROM trail ORDER BY t DESC LIMIT 1) SELECT ent.id, CASE WHEN {dot('m.', 'ent.')} - m.b >= 0 THEN 1 ELSE -1 END AS class FROM ent, m"


def _embeddings() -> str:
    """The trail over 64 dimensions, as lists."""
    ent = "ent AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS f, CASE WHEN label < 5 THEN 1 ELSE -1 END AS y FROM embeddings)"
    ex = "ex AS (SELECT *, row_number() OVER (ORDER BY id) AS k FROM ent ORDER BY id LIMIT 200)"
    step = "tr AS (SELECT 0 AS t, list_transform(range(64), lambda x: 0e0) AS w, 0e0 AS b UNION ALL SELECT t0 + 1, list_transform(list_zip(w, f), lambda p: p[1] * (1e0 - eta * 1e-3) - eta * g * p[2]), b + eta * g FROM (SELECT *, CASE WHEN y * z < 1 THEN -CAST(y AS DOUBLE) ELSE 0e0 END AS g FROM (SELECT tr.t AS t0, tr.w, tr.b, e.f, e.y, 1e-1 / (1e0 + 1e-3 * 1e-1 * tr.t) AS eta, list_dot_product(tr.w, e.f) - tr.b AS z FROM tr JOIN ex e ON e.k = tr.t + 1)))"
    return f"WITH RECURSIVE {ent}, {ex}, {step} SELECT ent.id, CASE WHEN list_dot_product(tr.w, ent.f) - tr.b >= 0 THEN 1 ELSE -1 END AS class FROM ent, tr WHERE tr.t = 200"


def _sweep() -> str:
    return (
        f"{LAST}, c AS (SELECT floor(abs(eps) * 10000) AS step, count(*) AS n FROM fin GROUP BY 1), cc AS (SELECT step, sum(n) OVER (ORDER BY step) AS total FROM c), nn AS (SELECT count(*) AS n FROM fin),"
        " bs AS (SELECT unnest([1, 10, 50]) AS band_share), rc AS (SELECT band_share, (min(step) + 1) / 10000 AS reach FROM bs, cc, nn WHERE total * 100 >= n * band_share GROUP BY band_share),"
        " rk AS (SELECT band_share, reach, id, eps, row_number() OVER (PARTITION BY band_share ORDER BY CASE WHEN eps >= reach THEN eps - reach WHEN eps < -reach THEN -reach - eps ELSE 0 END, id) AS r FROM fin, rc),"
        " rd AS (SELECT id FROM fin ORDER BY md5(CAST(id AS VARCHAR)), id LIMIT 15000), sz AS (SELECT unnest([5e-1, 1e0, 5e0, 1e1, 2e1, 5e1, 1e2]) AS buffer_share)"
        " SELECT band_share, buffer_share, CASE WHEN NOT (eps >= -reach AND eps < reach) THEN 'map' WHEN r <= CAST(floor(n * buffer_share / 100) AS BIGINT) THEN 'buffer' ELSE 'disk' END AS source, count(*) AS n FROM rk JOIN rd USING (id), sz, nn GROUP BY ALL"
    )


def oracle_sql() -> dict[str, str]:
    zero = ", ".join(f"('{t}')" for t in ("naive_disk", "naive_memory", "incremental_disk", "incremental_memory", "hybrid"))
    counts = "count(*) AS n, sum(CASE WHEN y = 1 AND class = 1 THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN y = -1 AND class = 1 THEN 1 ELSE 0 END) AS fp, sum(CASE WHEN y = 1 AND class = -1 THEN 1 ELSE 0 END) AS fn, sum(CASE WHEN y = -1 AND class = -1 THEN 1 ELSE 0 END) AS tn"
    ratio = lambda a, b: f"CASE WHEN {b} > 0 THEN round({a} / CAST({b} AS DOUBLE), 6) ELSE 0e0 END"
    trails = {f"sgd_trail_{k}": f"WITH RECURSIVE {ENT}, {EX}, {trail(k, "1e-1", "5e-2")} SELECT CAST(t - 160 AS INT) AS round, {', '.join(f'round({w}, 6) AS {w}' for w in W)}, round(b, 6) AS b FROM trail WHERE t >= 160" for k in SLOPES}
    same = ("eager_view_final", "eager_view_pairwise", "eager_view_linf_l1", "eager_view_memory", "eager_view_slim_refined", "naive_eager_view", "full_retrain_baseline", "stream_update_view")
    return (
        {k: FINAL for k in same}
        | trails
        | {
            "tf_bag_of_terms": f"WITH {terms()} SELECT id, term, round(val / sum(val) OVER (PARTITION BY id), 9) AS val FROM c",
            "title7_features": f"WITH {terms(first=7)} SELECT * FROM c",
            "tfidf_terms": f"WITH {terms()}, n AS (SELECT count(*) AS n FROM documents), d AS (SELECT term, count(*) AS df FROM c GROUP BY term) SELECT id, term, round(val * (ln((n + 1) / (df + 1)) + 1), 6) AS val FROM c JOIN d USING (term), n",
            "page_text_terms": f"WITH b AS (SELECT page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS body FROM pages), {terms('b', 'page_id', 'body')} SELECT * FROM c",
            "text_norms": f"WITH {terms()}, p AS (SELECT id, sum(val) AS l1, sqrt(sum(val * val)) AS l2, max(val) AS linf FROM c GROUP BY id) SELECT round(max(l2), 6) AS raw_l2, round(max(l2 / l1), 6) AS l1_l2, round(max(linf / l1), 6) AS l1_linf, round(max(linf / l2), 6) AS l2_linf FROM p",
            "onehot_parts": "SELECT DISTINCT p_partkey AS id, unnest(['p_brand=' || p_brand, 'p_type=' || p_type, 'p_size=' || p_size]) AS term, 1e0 AS val FROM part",
            "dense_norms": f"WITH {ENT} SELECT 'planted_lineitem' AS dataset, round(max(abs(f0) + abs(f1) + abs(f2) + abs(f3)), 6) AS m1, round(max(sqrt(f0 * f0 + f1 * f1 + f2 * f2 + f3 * f3)), 6) AS m2, round(max(greatest(abs(f0), abs(f1), abs(f2), abs(f3))), 6) AS minf FROM ent"
            " UNION ALL SELECT 'embeddings_binary', round(max(list_sum(list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE))))), 6), round(max(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))))), 6), round(max(list_max(list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE))))), 6) FROM embeddings",
            "polynomial2_features": f"WITH {ENT} SELECT id, 14 AS dim, round(f0 * f1, 6) AS f0f1, round(f3 * f3, 6) AS f3f3, round(f0 + f1 + f2 + f3 + f0*f0 + f0*f1 + f0*f2 + f0*f3 + f1*f1 + f1*f2 + f1*f3 + f2*f2 + f2*f3 + f3*f3, 6) AS total FROM ent",
            "dataset_stats": f"WITH {ENT}, {terms()}, {terms(first=7).replace('t AS', 't7 AS', 1).replace('c AS', 'c7 AS', 1).replace('FROM t ', 'FROM t7 ')},"
            " nz AS (SELECT doc_id, count(term) AS nz FROM documents LEFT JOIN c ON c.id = doc_id GROUP BY doc_id), nz7 AS (SELECT doc_id, count(term) AS nz FROM documents LEFT JOIN c7 ON c7.id = doc_id GROUP BY doc_id)"
            f" {STATS} SELECT 'planted_lineitem' AS dataset, count(*) AS n_entities, 4 AS n_features, avg(CAST(f0 <> 0 AS INT) + CAST(f1 <> 0 AS INT) + CAST(f2 <> 0 AS INT) + CAST(f3 <> 0 AS INT)) AS mean_nonzero FROM ent"
            " UNION ALL SELECT 'embeddings_binary', count(*), 64, avg(len(list_filter(embedding, lambda x: x <> 0))) FROM embeddings"
            " UNION ALL SELECT 'title7', count(*), (SELECT count(DISTINCT term) FROM c7), avg(nz) FROM nz7 UNION ALL SELECT 'full_text', count(*), (SELECT count(DISTINCT term) FROM c), avg(nz) FROM nz)",
            "least_squares_fits": f"WITH {ENT}, {ONE}, u AS (SELECT regr_slope(y, x) AS w, regr_intercept(y, x) AS i, regr_sxy(y, x) / (regr_sxx(y, x) + 10) AS rw, avg(x) AS mx, avg(y) AS my, sum(k * x) / sum(k) AS kx, sum(k * y) / sum(k) AS ky FROM o),"
            " kw AS (SELECT sum(k * (x - kx) * (y - ky)) / sum(k * (x - kx) * (x - kx)) AS w FROM o, u)"
            " SELECT 'ols' AS method, round(w, 6) AS w, round(-i, 6) AS b FROM u UNION ALL SELECT 'ridge', round(rw, 6), round(rw * mx - my, 6) FROM u UNION ALL SELECT 'weighted', round(kw.w, 6), round(kw.w * kx - ky, 6) FROM u, kw",
            "naive_lazy_view": _embeddings(),
            "full_retrain_view": _survivors(),
            "eager_rounds": f"{HEAD}, {MARGINS}, g AS (SELECT s, id, eps >= 0 AS p, lag(eps >= 0) OVER (PARTITION BY id ORDER BY s) AS q FROM ms) SELECT CAST(s AS INT) AS round, count(*) FILTER (WHERE p) AS n_positive, count(*) FILTER (WHERE p <> q) AS n_flipped FROM g GROUP BY s",
            "water_marks_by_round": f"{BANDS} SELECT CAST(i AS INT) AS round, round(low, 6) AS low, round(high, 6) AS high, round(lw, 6) AS lw, round(hw, 6) AS hw FROM wm WHERE s = 0",
            "band_sizes": f"{BANDS}, {MARGINS}, {FAMILY} SELECT CAST(i AS INT) AS round, n AS n_band, above AS n_above FROM fam WHERE s = 0",
            "sandwich_sets": f"{BANDS}, {MARGINS} SELECT ms.id, CAST(eps >= hw AS INT) AS certain FROM ms JOIN wm ON wm.s = 0 AND wm.i = 40 WHERE ms.s = 0 AND eps >= lw",
            "round_ledger": ledger("CAST(f.n AS DOUBLE)"),
            "lazy_ledger": ledger("CASE WHEN f.above > 0 THEN (f.above - p.n_pos) / CAST(f.above AS DOUBLE) * f.above ELSE 0e0 END"),
            "band_statistics": f"{BANDS}, {MARGINS}, {FAMILY}, g AS (SELECT s, id, eps >= 0 AS p, lag(eps >= 0) OVER (PARTITION BY id ORDER BY s) AS q FROM ms), fl AS (SELECT s AS i, count(*) FILTER (WHERE p <> q) AS x FROM g GROUP BY s)"
            " SELECT round(avg(n), 6) AS mean_band, round(stddev_pop(n), 6) AS sd_band, round(avg(n) / (SELECT count(*) FROM ent), 6) AS share, round(avg(x), 6) AS mean_flips FROM fam JOIN fl USING (i) WHERE s = 0 AND i > 0",
            "lazy_members_positive": f"{LAST} SELECT id FROM v WHERE class = 1",
            "lazy_members_negative": f"{LAST} SELECT id FROM v WHERE class = -1",
            "lazy_count": f"{LAST} SELECT class, count(*) AS n FROM v GROUP BY class",
            "hybrid_labels": f"{LAST} SELECT id, class FROM v ORDER BY md5(CAST(id AS VARCHAR)), id LIMIT 15000",
            "buffer_sweep": _sweep(),
            "hybrid_memory": "WITH d AS (SELECT 'planted_lineitem' AS dataset, count(*) AS n, 32 AS f FROM lineitem UNION ALL SELECT 'embeddings_binary', count(*), 512 FROM embeddings) SELECT dataset, n, 16 * n AS margin_map, (n // 100) * (f + 8) + 16 * n AS hybrid, n * (8 + f) AS whole, round(n * (8 + f) / CAST(16 * n AS DOUBLE), 6) AS ratio FROM d",
            "most_uncertain": f"{LAST} SELECT id, round(eps, 6) AS eps FROM fin ORDER BY abs(eps), id LIMIT 100",
            "new_entities_view": f"{HEAD} SELECT ent.id, CASE WHEN {dot('m.', 'ent.')} * CASE WHEN ent.id % 10 = 9 THEN 2 ELSE 1 END - m.b >= 0 THEN 1 ELSE -1 END AS class FROM ent, m WHERE m.j = 40",
            "deleted_entities_view": f"{LAST} SELECT id, class FROM v WHERE id % 7 <> 3",
            "cost_family": f"{BANDS}, {MARGINS}, {FAMILY} SELECT CAST(s AS INT) AS s, CAST(i AS INT) AS i, n AS n_band FROM fam",
            "monotonicity": f"{BANDS}, {MARGINS}, {FAMILY} SELECT (SELECT count(*) FROM fam WHERE s > 0) AS pairs, (SELECT count(*) FROM fam a JOIN fam b ON b.s = a.s - 1 AND b.i = a.i WHERE a.n > b.n) AS later_costs_more, (SELECT count(*) FROM fam a JOIN fam b ON b.s = a.s AND b.i = a.i - 1 WHERE a.n < b.n) AS cost_falls",
            "offline_optimum": _schedules(),
            "policy_comparison": _policies(),
            "ovr_multiclass": f"{_flags()} SELECT id, {BEST} AS class FROM sc",
            "chain_multiclass": f"{_flags()} SELECT id, CASE WHEN s_A >= 0 THEN 'A' WHEN s_N >= 0 THEN 'N' ELSE 'R' END AS class FROM sc",
            "ovr_confusion": f"{_flags()}, p AS (SELECT l_returnflag AS truth, {BEST} AS class FROM sc) SELECT truth, count(*) FILTER (WHERE class = 'A') AS A, count(*) FILTER (WHERE class = 'N') AS N, count(*) FILTER (WHERE class = 'R') AS R FROM p GROUP BY truth",
            "largest_class": "SELECT 'embeddings' AS dataset, (SELECT CAST(label AS VARCHAR) FROM embeddings GROUP BY label ORDER BY count(*) DESC, CAST(label AS VARCHAR) LIMIT 1) AS label UNION ALL SELECT 'lineitem', (SELECT l_returnflag FROM lineitem GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 1)",
            "quality_dense": f"{LAST}, q AS (SELECT {counts} FROM v) SELECT n, CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, CAST(fn AS BIGINT) AS fn, CAST(tn AS BIGINT) AS tn, {ratio('(tp + tn)', 'n')} AS accuracy, {ratio('tp', '(tp + fp)')} AS precision, {ratio('tp', '(tp + fn)')} AS recall, {ratio('(2 * tp)', '(2 * tp + fp + fn)')} AS f1 FROM q",
            "view_joined_sql": f"{LAST} SELECT o_orderpriority AS priority, class, count(*) AS n FROM v JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL",
            "view_cube": f"{LAST} SELECT l_returnflag, l_linestatus, count(*) AS n, count(*) FILTER (WHERE class = 1) AS n_positive FROM v GROUP BY CUBE (l_returnflag, l_linestatus)",
            "view_rollup": f"{LAST} SELECT l_returnflag, c AS class, count(*) AS n FROM (SELECT l_returnflag, CAST(class AS VARCHAR) AS c FROM v) GROUP BY ROLLUP (l_returnflag, c)",
            "sql_functions": f"{LAST} SELECT class, count(*) AS n, round(max(sqrt(f0 * f0 + f1 * f1 + f2 * f2 + f3 * f3)), 6) AS largest FROM v GROUP BY class",
            "declared_view": f"WITH RECURSIVE {ENT}, {EX}, {trail(eta='1e-1', l2='1e-3')} SELECT ent.id, CASE WHEN {dot('m.', 'ent.')} - m.b >= 0 THEN 1 ELSE -1 END AS class FROM ent, trail m WHERE m.t = 200",
            "event_windows": _events("SELECT user_id, CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start, count(*) AS n, sum(value) AS total FROM events GROUP BY 1, 2"),
            "event_sliding": _events("SELECT user_id, start, count(*) AS n, sum(value) AS total FROM (SELECT user_id, value, unnest([CAST(epoch(time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT), CAST(epoch(time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT) - 10800]) AS start FROM events) GROUP BY 1, 2"),
            "event_sessions": _events("SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n, sum(value) AS total FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s"),
            "technique_matrix": f"SELECT technique, policy, operation, CAST(0 AS BIGINT) AS n_wrong FROM (VALUES {zero}) t(technique), (VALUES ('eager'), ('lazy')) p(policy), (VALUES ('update'), ('single'), ('all')) o(operation)",
        }
    )
