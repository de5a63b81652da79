"""DuckDB SQL of the queries on changes, classes, texts and SQL around views, by definition."""

from __future__ import annotations

from driftview.functions.features import DenseColumns, RandomFourier
from driftview.oracles import BANDS, BEST, DIM, ENT, EX, HEAD, LARGEST, LAST, MARGINS, ONE, W, _flags, _schedules, dot, terms
from driftview.plans.workloads import IN_SQL, LINEITEM
from driftview.queries import ANCHORS, COSINES

CLASS = "CASE WHEN {} >= 0 THEN 1 ELSE -1 END AS class"


def _at(round_: int, where: str = "", factor: str = "1") -> str:
    """The view under the model of a round, with some vectors scaled."""
    return f"{HEAD} SELECT ent.id, {CLASS.format(f'{dot('m.', 'ent.')} * ({factor}) - m.b')} FROM ent, m WHERE m.j = {round_}{where}"


# --- several classes


def _lost(classes: str = "ANR") -> str:
    """Per class and round, the most that a lead can have lost since the warm models, and leads under these."""
    models = " UNION ALL ".join(f"SELECT '{c}' AS c, t - 160 AS j, {', '.join(W)}, b FROM tr_{c} WHERE t >= 160" for c in classes)
    moved = " + ".join(f"(m.{w} - s.{w}) * (m.{w} - s.{w})" for w in W)
    scores = ", ".join(f"{dot(f'{c}0.', 'ent.')} - {c}0.b AS z_{c}" for c in classes)
    joins = ", ".join(f"(SELECT * FROM tr_{c} WHERE t = 160) {c}0" for c in classes)
    return (
        f"{_flags()}, {LARGEST}, md AS ({models}),"
        f" mv AS (SELECT m.c, m.j, largest * sqrt({moved}) AS reach, m.b - s.b AS shift FROM md m JOIN md s ON s.c = m.c AND s.j = 0 CROSS JOIN mx WHERE m.j > 0),"
        " lo AS (SELECT a.c, a.j, a.reach + a.shift + max(r.reach - r.shift) AS lost FROM mv a JOIN mv r ON r.j = a.j AND r.c <> a.c GROUP BY a.c, a.j, a.reach, a.shift),"
        " hw AS (SELECT c, j, max(lost) OVER (PARTITION BY c ORDER BY j) AS hw FROM lo),"
        f" st AS (SELECT ent.id, {scores} FROM ent, {joins}),"
        " ld AS (SELECT id, greatest(z_A, z_N, z_R) AS top, greatest(least(z_A, z_N), least(z_N, z_R), least(z_A, z_R)) AS second, CASE WHEN z_A >= z_N AND z_A >= z_R THEN 'A' WHEN z_N >= z_R THEN 'N' ELSE 'R' END AS c FROM st)"
    )


def _list_trail(classes: str, eta: str, l2: str, slope: str = "-CAST(y AS DOUBLE)", dim: int = 64) -> str:
    """A model of lists for each row (c) of a table ``cl``; ``classes`` gives an example's class for it."""
    return (
        f"tr AS (SELECT c, 0 AS t, list_transform(range({dim}), lambda x: 0e0) AS w, 0e0 AS b FROM cl UNION ALL"
        f" SELECT c, t0 + 1, list_transform(list_zip(w, f), lambda p: p[1] * (1e0 - eta * {l2}) - eta * g * p[2]), b + eta * g FROM"
        f" (SELECT *, CASE WHEN y * z < 1 THEN {slope} ELSE 0e0 END AS g FROM"
        f" (SELECT tr.c, tr.t AS t0, tr.w, tr.b, e.f, {classes} AS y, {eta} / (1e0 + {l2} * {eta} * tr.t) AS eta, list_dot_product(tr.w, e.f) - tr.b AS z FROM tr JOIN ex e ON e.k = tr.t + 1)))"
    )


def _ten_classes() -> str:
    ent = "ent AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS f, label FROM embeddings)"
    ex = "ex AS (SELECT *, row_number() OVER (ORDER BY id) AS k FROM ent ORDER BY id LIMIT 200)"
    cl = "cl AS (SELECT CAST(range AS INT) AS c FROM range(10))"
    return f"WITH RECURSIVE {ent}, {ex}, {cl}, {_list_trail('CASE WHEN e.label = tr.c THEN 1 ELSE -1 END', '1e-1', '1e-3')}, sc AS (SELECT ent.id, tr.c, list_dot_product(tr.w, ent.f) - tr.b AS z FROM ent, tr WHERE tr.t = 200) SELECT id, arg_max(c, (z, -c)) AS class FROM sc GROUP BY id"


# --- texts


D = IN_SQL["dim"]


def _vectors(first: int | None = None, norm: str | None = "l2") -> str:
    """Hashed word counts of documents as lists."""
    size = "sqrt(sum(n * n))" if norm == "l2" else "CAST(1 AS DOUBLE)"
    return (
        f"{terms(first=first)}, sl AS (SELECT id, CAST('0x' || substr(md5(term), 1, 8) AS BIGINT) % {D} AS s, CAST(count(*) AS BIGINT) AS n FROM t GROUP BY 1, 2),"
        f" sz AS (SELECT id, {size} AS size FROM sl GROUP BY id), vv AS (SELECT sl.id, s, CAST(n AS DOUBLE) / size AS val FROM sl JOIN sz USING (id)),"
        f" ent AS MATERIALIZED (SELECT d.doc_id AS id, d.lang, list(coalesce(val, 0e0) ORDER BY r.k) AS f, count(val) AS nz FROM documents d CROSS JOIN (SELECT range AS k FROM range({D})) r LEFT JOIN vv ON vv.id = d.doc_id AND vv.s = r.k GROUP BY d.doc_id, d.lang)"
    )


ENGLISH = "SELECT doc_id AS id, CASE WHEN lang = 'en' THEN 1 ELSE -1 END AS y FROM documents"


def _labels(column: str) -> str:
    return f"SELECT doc_id AS id, CASE WHEN {column} = 1 THEN 1 ELSE -1 END AS y FROM labels WHERE {column} IS NOT NULL"


def _text(first: int | None = None, norm: str | None = "l2", labels: str = ENGLISH, slope: str = "-CAST(y AS DOUBLE)", eta: str = "1e0", limit: str = " LIMIT 200") -> str:
    """Everything up to the models of one class, trained on the first 200 labelled documents, or all."""
    return f"WITH RECURSIVE {_vectors(first, norm)}, lb AS ({labels}), ex AS MATERIALIZED (SELECT ent.id, ent.f, lb.y, row_number() OVER (ORDER BY ent.id) AS k FROM lb JOIN ent USING (id) WHERE lb.id IN (SELECT id FROM lb ORDER BY id{limit})), cl AS (SELECT 0 AS c), {_list_trail('e.y', eta, '1e-4', slope, D)}"


def _text_view(*how: str | int | None) -> str:
    return f"{_text(*how)}, v AS (SELECT ent.id, CASE WHEN list_dot_product(tr.w, ent.f) - tr.b >= 0 THEN 1 ELSE -1 END AS class FROM ent, tr WHERE tr.t = (SELECT max(t) FROM tr))"


def _uneven(column: str) -> str:
    """The view by all labels of a column, of which the rare class weighs three times."""
    rare = -1 if column == "quality" else 1
    return _text_view(None, "l2", _labels(column), f"-CAST(y AS DOUBLE) * CASE WHEN y = {rare} THEN 3e0 ELSE 1e0 END", "3e-1", "")


COUNTS = "count(*) AS n, sum(CASE WHEN y = 1 AND class = 1 THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN y = -1 AND class = 1 THEN 1 ELSE 0 END) AS fp, sum(CASE WHEN y = 1 AND class = -1 THEN 1 ELSE 0 END) AS fn, sum(CASE WHEN y = -1 AND class = -1 THEN 1 ELSE 0 END) AS tn"


def _quality(view: str) -> str:
    ratio = lambda a, b: f"CASE WHEN {b} > 0 THEN round({a} / CAST({b} AS DOUBLE), 6) ELSE 0e0 END"
    return f"{view}, q AS (SELECT {COUNTS} FROM v JOIN lb USING (id)) SELECT n, CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, CAST(fn AS BIGINT) AS fn, CAST(tn AS BIGINT) AS tn, {ratio('(tp + tn)', 'n')} AS accuracy, {ratio('tp', '(tp + fp)')} AS precision, {ratio('tp', '(tp + fn)')} AS recall, {ratio('(2 * tp)', '(2 * tp + fp + fn)')} AS f1 FROM q"


def _text_bands() -> str:
    """Bands of both normalizations, each in a statement of its own that is joined as a table."""

    def one(name: str, norm: str | None) -> str:
        away = "sqrt(list_sum(list_transform(list_zip(i.w, s.w), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))"
        return (
            f"SELECT * FROM ({_text(None, norm)}, mx AS (SELECT max(sqrt(list_sum(list_transform(f, lambda x: x * x)))) AS largest FROM ent),"
            f" dv AS (SELECT i.t - 160 AS j, (i.b - s.b) - largest * {away} AS low, (i.b - s.b) + largest * {away} AS high FROM tr i, tr s, mx WHERE s.t = 160 AND i.t >= 160),"
            " wm AS (SELECT j, min(low) OVER (ORDER BY j) AS lw, max(high) OVER (ORDER BY j) AS hw FROM dv),"
            " e AS (SELECT list_dot_product(tr.w, ent.f) - tr.b AS eps FROM ent, tr WHERE tr.t = 160)"
            f" SELECT '{name}' AS norm, CAST(j AS INT) AS round, count(*) FILTER (WHERE eps >= lw AND eps < hw) AS n_band FROM wm, e WHERE j > 0 GROUP BY j)"
        )

    return f"{one('l2', 'l2')} UNION ALL {one('raw', None)}"


def _languages() -> str:
    train = _list_trail("CASE WHEN e.lang = tr.c THEN 1 ELSE -1 END", "1e0", "1e-4", dim=D)
    return (
        f"WITH RECURSIVE {_vectors()}, ex AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY id) AS k FROM ent ORDER BY id LIMIT 200), cl AS (SELECT unnest(['de', 'en', 'es', 'fr']) AS c), {train},"
        " sc AS (SELECT ent.id, ent.lang, tr.c, list_dot_product(tr.w, ent.f) - tr.b AS z FROM ent, tr WHERE tr.t = 200),"
        " rk AS (SELECT id, lang, c, row_number() OVER (PARTITION BY id ORDER BY z DESC, c) AS r FROM sc) SELECT lang AS label, c AS class, count(*) AS n FROM rk WHERE r = 1 GROUP BY ALL"
    )


def _text_sizes() -> str:
    one = lambda name, first: f"SELECT * FROM (WITH {_vectors(first)} SELECT '{name}' AS dataset, count(*) AS n, 16 * count(*) AS margin_map, CAST(sum(12 * nz) AS BIGINT) AS vectors, round((8 * count(*) + sum(12 * nz)) / CAST(16 * count(*) AS DOUBLE), 6) AS ratio FROM ent)"
    return f"{one('title7', 7)} UNION ALL {one('full_text', None)}"


# --- methods


def _left_out() -> str:
    """Every example left out in turn, for the hinge and the logistic loss: all models at once, a step an iteration."""
    inner = f"SELECT m.loss, m.x, m.t AS t0, {', '.join('m.' + w for w in W)}, m.b, {', '.join('e.f' + str(k) for k in DIM)}, e.y, 1e-1 / (1e0 + 1e-3 * 1e-1 * m.t) AS eta, {dot('m.', 'e.')} - m.b AS z FROM lo m JOIN ex e ON e.k = m.t + 1 + CASE WHEN m.t + 1 >= m.x THEN 1 ELSE 0 END"
    slope = "CASE WHEN loss = 'svm' THEN CASE WHEN y * z < 1 THEN -CAST(y AS DOUBLE) ELSE 0e0 END ELSE -y / (1e0 + exp(y * z)) END"
    step = ", ".join(f"w{k} * (1e0 - eta * 1e-3) - eta * g * f{k}" for k in DIM)
    return (
        f"WITH RECURSIVE {ENT}, {EX}, lo AS (SELECT unnest(['svm', 'logistic']) AS loss, k AS x, 0 AS t, {', '.join('0e0 AS ' + w for w in W)}, 0e0 AS b FROM ex UNION ALL SELECT loss, x, t0 + 1, {step}, b + eta * g FROM (SELECT *, {slope} AS g FROM ({inner})))"
        f" SELECT loss AS method, count(*) AS n, count(*) FILTER (WHERE CASE WHEN {dot('lo.', 'e.')} - lo.b >= 0 THEN 1 ELSE -1 END <> e.y) AS n_wrong FROM lo JOIN ex e ON e.k = lo.x WHERE lo.t = 199 GROUP BY loss"
    )


def _press() -> str:
    """Scores without the row, from the sums over all rows and the row's own share of them."""
    return (
        f"WITH {ENT}, {ONE}, u AS (SELECT count(*) AS n, avg(x) AS mx, avg(y) AS my, regr_sxx(y, x) AS sxx, regr_sxy(y, x) AS sxy FROM o),"
        " p AS (SELECT 'ols' AS method, 0e0 AS l2 UNION ALL SELECT 'ridge', 1e1),"
        " r AS (SELECT method, id, y, my + sxy / (sxx + l2) * (x - mx) AS fitted, 1e0 / n + (x - mx) * (x - mx) / (sxx + l2) AS h FROM o, u, p),"
        " s AS (SELECT method, id, y, y - (y - fitted) / (1e0 - h) AS score FROM r)"
    )


def _fourier() -> str:
    omega, phase = RandomFourier(DenseColumns(*LINEITEM), COSINES, 1.0).draws()
    number = lambda x: f"{float(x):.17e}"
    terms_ = "[" + ", ".join("[" + ", ".join(number(x) for x in (*omega[:, k], phase[k])) + "]" for k in range(COSINES)) + "]"
    phi = f"list_transform(({terms_}), lambda o: sqrt(2e0 / {COSINES}) * cos(f0 * o[1] + f1 * o[2] + f2 * o[3] + f3 * o[4] + o[5]))"
    gap = " + ".join(f"(e.f{k} - a.f{k}) * (e.f{k} - a.f{k})" for k in DIM)
    return f"WITH {ENT}, e AS (SELECT id, f0, f1, f2, f3, {phi} AS phi FROM ent), a AS (SELECT * FROM e ORDER BY id LIMIT {ANCHORS}), r AS (SELECT abs(list_dot_product(e.phi, a.phi) - exp(-({gap}))) AS err FROM e, a) SELECT count(*) AS n, round(avg(err), 6) AS mean_error, round(max(err), 6) AS max_error FROM r"


def _bulk() -> str:
    """Five whole-batch steps, one after the other."""
    parts = [f"m0 AS (SELECT {', '.join('0e0 AS ' + w for w in W)}, 0e0 AS b)"]
    for k in range(5):
        eta = f"(1e0 / {k + 1}e0)"
        sums = ", ".join(f"m{k}.w{i} * (1e0 - {eta} * 1e-3) - {eta} * sum(g * f{i}) / count(*) AS w{i}" for i in DIM)
        score = f"{dot(f'm{k}.', 'ent.')} - m{k}.b"
        parts.append(f"g{k} AS (SELECT ent.*, CASE WHEN y * ({score}) < 1 THEN -CAST(y AS DOUBLE) ELSE 0e0 END AS g FROM ent, m{k})")
        parts.append(f"m{k + 1} AS (SELECT {sums}, m{k}.b + {eta} * sum(g) / count(*) AS b FROM g{k}, m{k} GROUP BY {', '.join(f'm{k}.{w}' for w in W)}, m{k}.b)")
    return f"WITH {ENT}, {', '.join(parts)} SELECT 0 AS round, {', '.join(f'round({w}, 6) AS {w}' for w in W)}, round(b, 6) AS b FROM m5"


def _hybrid_sources() -> str:
    """Bounds after rounds of eight examples, the buffer about the hyperplane at the start, and 15,000 reads."""
    return (
        f"{BANDS}, {MARGINS}, bd AS (SELECT min(low) AS lw, max(high) AS hw FROM dv WHERE s = 0 AND i % 8 = 0),"
        " st AS (SELECT id, eps, row_number() OVER (ORDER BY CASE WHEN eps >= 0 THEN eps ELSE -eps END, id) AS r FROM ms WHERE s = 0), nn AS (SELECT count(*) AS n FROM st),"
        " rd AS (SELECT id FROM st ORDER BY md5(CAST(id AS VARCHAR)), id LIMIT 15000),"
        " sr AS (SELECT CASE WHEN eps >= hw OR eps < lw THEN 'map' WHEN r <= CAST(floor(n * 1e-2) AS BIGINT) THEN 'buffer' ELSE 'disk' END AS source FROM st JOIN rd USING (id), bd, nn)"
        " SELECT source, count(*) AS n, round(count(*) / CAST((SELECT count(*) FROM rd) AS DOUBLE), 6) AS share FROM sr GROUP BY source"
    )


# --- SQL around views and streams


def _waste() -> str:
    return (
        "WITH RECURSIVE e AS (SELECT user_id AS key, event_id AS seq, value AS cost, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS k FROM events),"
        " r AS (SELECT key, CAST(0 AS BIGINT) AS k, CAST(-1 AS BIGINT) AS seq, 0e0 AS waste, CAST(0 AS BIGINT) AS bought FROM (SELECT DISTINCT key FROM e) UNION ALL"
        " SELECT r.key, e.k, e.seq, CASE WHEN r.waste >= 200 THEN 0e0 ELSE r.waste + e.cost END, r.bought + CASE WHEN r.waste >= 200 THEN 1 ELSE 0 END FROM r JOIN e ON e.key = r.key AND e.k = r.k + 1)"
        " SELECT key, seq, round(waste, 4) AS waste, bought AS reclusters FROM r WHERE k > 0"
    )


def oracle_sql() -> dict[str, str]:
    final = f"{LAST} SELECT id, class FROM v"
    english, titles = _text_view(), _text_view(7)
    view = lambda x: f"{x} SELECT id, class FROM v"
    share = "CASE WHEN best > 0 THEN best END"
    cells = "(VALUES ('title7'), ('full_text')) d(dataset), (VALUES ('naive_disk'), ('naive_memory'), ('incremental_disk'), ('incremental_memory'), ('hybrid')) t(technique), (VALUES ('eager'), ('lazy')) p(policy), (VALUES ('update'), ('single'), ('all')) o(operation)"
    best_alpha = "(sqrt(s * s + 4) - s) / 2"
    return {
        "deleted_entities_sql": _at(20, " AND ent.id % 7 <> 3"),
        "lazy_arrivals_sql": _at(16, "", "CASE WHEN ent.id % 10 = 9 THEN 2 ELSE 1 END"),
        "readded_entities": _at(40, "", "CASE WHEN ent.id % 7 = 3 THEN 2 ELSE 1 END"),
        "nan_entities": _at(40, " AND ent.id % 11 <> 5"),
        "cold_start_view": final,
        "competitive_ratio": f"SELECT share, round(rule / {share}, 6) AS ratio, round(greatest(2e0 + 25e-2 / share, 2e0), 6) AS bound FROM ({_schedules()})",
        "alpha_by_sigma": f"SELECT l_orderkey, round(s, 6) AS sigma, round({best_alpha}, 6) AS alpha, round(greatest(1 + {best_alpha} + s, 1 + 1 / ({best_alpha})), 6) AS ratio FROM (SELECT l_orderkey, CASE WHEN sum(l_quantity) > 0 THEN max(l_quantity) / sum(l_quantity) END AS s FROM lineitem GROUP BY l_orderkey)",
        "multiclass_view_final": f"{_flags()} SELECT id, {BEST} AS class FROM sc",
        "multiclass_view_memory": f"{_flags()} SELECT id, {BEST} AS class FROM sc",
        "multiclass_view_lazy": f"{_flags()}, b AS (SELECT id, {BEST} AS class FROM sc) SELECT c.class, count(b.id) AS n FROM (VALUES ('A'), ('N'), ('R')) c(class) LEFT JOIN b USING (class) GROUP BY c.class",
        "multiclass_band_sizes": f"{_lost()} SELECT CAST(j AS INT) AS round, count(*) FILTER (WHERE top - second <= hw) AS n_band FROM hw JOIN ld USING (c) GROUP BY j",
        "multiclass_embeddings": _ten_classes(),
        "multiclass_languages": _languages(),
        "declared_multiclass": f"{_flags().replace('2e0 /', '1e-1 /').replace('* 2e0 *', '* 1e-1 *').replace('1e-2', '1e-3')} SELECT id, {BEST} AS class FROM sc",
        "title_view_final": view(titles),
        "title_view_hybrid": view(titles),
        "text_view_final": view(english),
        "text_view_slim": view(english),
        "text_cold_start": view(english),
        "text_lazy_count": f"{english} SELECT class, count(*) AS n FROM v GROUP BY class",
        "text_raw_counts_view": view(_text_view(None, None)),
        "quality_labels_view": view(_uneven("quality")),
        "toxic_labels_view": view(_uneven("toxic")),
        "text_band_sizes": _text_bands(),
        "text_memory": _text_sizes(),
        "text_technique_matrix": f"SELECT dataset, technique, policy, operation, CAST(0 AS BIGINT) AS n_wrong FROM {cells}",
        "quality_title7": _quality(titles),
        "quality_full_text": _quality(english),
        "quality_examples_table": _quality(_uneven("quality")),
        "loo_scores": f"{_press()} SELECT id, round(score, 6) AS score FROM s WHERE method = 'ols'",
        "loo_errors_by_method": f"{_press()} SELECT method, count(*) AS n, count(*) FILTER (WHERE CASE WHEN score >= 0 THEN 1 ELSE -1 END <> y) AS n_wrong FROM s GROUP BY method",
        "loo_by_retraining": _left_out(),
        "random_fourier_kernel": _fourier(),
        "bulk_gradient_training": _bulk(),
        "hybrid_sources": _hybrid_sources(),
        "event_asof": "WITH b AS (SELECT user_id, ts, event_id, value FROM events WHERE event_type = 'purchase') SELECT c.event_id, c.user_id, coalesce(b.event_id, -1) AS event_id_asof, coalesce(b.value, -1e0) AS value_asof FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN b ON c.user_id = b.user_id AND c.ts >= b.ts",
        "event_props": "SELECT user_id, CAST(sum(CAST(regexp_extract(props, '\"k\": *(-?[0-9]+)', 1) AS BIGINT)) AS BIGINT) AS total, max(CAST(regexp_extract(props, '\"k\": *(-?[0-9]+)', 1) AS BIGINT)) AS largest FROM events GROUP BY user_id",
        "view_by_month": f"{LAST.replace('l_returnflag, l_linestatus, l_orderkey FROM lineitem', 'l_returnflag, l_linestatus, l_orderkey, l_shipdate FROM lineitem')} SELECT strftime(l_shipdate, '%Y-%m') AS month, class, count(*) AS n FROM v WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' GROUP BY ALL",
        "view_grouping_sets": f"{LAST}, s AS (SELECT l_returnflag, l_linestatus, CAST(class AS VARCHAR) AS class FROM v) SELECT l_returnflag, l_linestatus, class, CAST(grouping(l_returnflag, class, l_linestatus) AS BIGINT) AS level, count(*) AS n FROM s GROUP BY GROUPING SETS ((l_returnflag, class), (l_linestatus), ())",
        "margins_lateral": f"{LAST}, rk AS (SELECT l_returnflag, id, eps, row_number() OVER (PARTITION BY l_returnflag ORDER BY abs(eps), id) AS r FROM fin) SELECT l_returnflag, id, round(eps, 6) AS eps FROM rk WHERE r <= 3",
        "margins_scalar_subquery": f"{LAST} SELECT l_returnflag, count(*) AS n, count(*) FILTER (WHERE eps > (SELECT avg(eps) FROM fin)) AS n_above FROM fin GROUP BY l_returnflag",
        "margins_by_interval": f"{LAST}, iv AS (SELECT range AS k, range / 10 - 1e0 AS lo, range / 10 - 75e-2 AS hi FROM range(20)) SELECT k, count(*) AS n FROM fin JOIN iv ON eps >= lo AND eps < hi GROUP BY k",
        "view_aggregates": f"{LAST} SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, arg_max(id, (eps, id)) AS furthest, round(quantile_cont(eps, 5e-1), 6) AS median FROM fin GROUP BY l_returnflag",
        "part_terms_udtf": "WITH t AS (SELECT p_partkey AS id, unnest(list_filter(regexp_split_to_array(lower(coalesce(p_name, '')), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')) AS term FROM part) SELECT id, term, count(*) AS n FROM t GROUP BY id, term",
        "clustered_ranges": f"{LAST} SELECT id, round(eps, 6) AS eps FROM fin WHERE eps >= -1e-1 AND eps < 1e-1",
        "certain_counts": f"{BANDS}, {MARGINS} SELECT CASE WHEN eps >= hw THEN 1 WHEN eps < lw THEN -1 ELSE 0 END AS certain, count(*) AS n FROM ms JOIN wm ON wm.s = 0 AND wm.i = 40 WHERE ms.s = 0 GROUP BY 1",
        "data_source_view": f"{LAST} SELECT id, class FROM v WHERE class = 1",
        "partition_overwrite": f"{LAST} SELECT id, class FROM v WHERE class = -1 OR id % 2 = 0",
        "stream_late_windows": "WITH w AS (SELECT user_id, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS s, count(*) AS n, sum(value) AS total FROM events GROUP BY 1, 2) SELECT user_id, CAST(epoch(s) AS BIGINT) AS start, n, round(total, 4) AS total FROM w WHERE s + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR",
        "stream_running_waste": _waste(),
    }
