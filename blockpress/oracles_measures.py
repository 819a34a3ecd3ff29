"""DuckDB SQL for ``queries_measures`` and ``queries_reports``."""

from __future__ import annotations

from blockpress.oracles import BLOCKS, CHANCES, GRID, MEASURED, LINE_CELLS, _entropy, _h2, _links

MODEL_GRID = f"WITH {GRID}, g AS (SELECT DISTINCT p0, p1, k, mean FROM forms), "
MEASURED_GRID = f"WITH {MEASURED}, g AS (SELECT DISTINCT line, p0, p1, k, mean FROM forms), "
TIGHT = f"((k - 1) / k * {_h2('p0')} + {_h2('p1')} / k)"
SLACK = "({h} + CASE WHEN k > 2 THEN {e} * log2(k - 1) ELSE 0 END)"


def _slack(err: str) -> str:
    return SLACK.format(h=_h2(err), e=err)


def _cell(i: int, j: int) -> str:
    one = f"(t >> {2 * i + j}) & 1 = 1"
    return f"(CASE WHEN ((l >> {i}) & 1) = ((l >> {2 + j}) & 1) THEN CASE WHEN {one} THEN p1 ELSE 1 - p1 END ELSE CASE WHEN {one} THEN p0 ELSE 1 - p0 END END)"


#: All 2 x 2 binary tables under all labels, with two row and two column labels: their chances.
TINY = f"""cells AS (SELECT unnest(range(16)) AS t), labels AS (SELECT unnest(range(16)) AS l),
    q AS (SELECT line, p0, p1, t, l, {" * ".join(_cell(i, j) for i in (0, 1) for j in (0, 1))} / 16 AS chance FROM chances, cells, labels)"""

ORACLES: dict[str, str] = {
    "null_symbols": """WITH d AS (SELECT lang, quality, toxic FROM documents LEFT JOIN labels USING (doc_id)), s AS (
        SELECT 0 AS col_id, dense_rank() OVER (ORDER BY lang NULLS LAST) - 1 AS code FROM d UNION ALL SELECT 1, dense_rank() OVER (ORDER BY quality NULLS LAST) - 1 FROM d
        UNION ALL SELECT 2, dense_rank() OVER (ORDER BY toxic NULLS LAST) - 1 FROM d) SELECT col_id::INT AS col_id, code::INT AS code, count(*) AS cnt FROM s GROUP BY ALL""",
    "numeric_images": """WITH c AS (SELECT dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS a, dense_rank() OVER (ORDER BY o_orderstatus) - 1 AS b FROM orders),
        k AS (SELECT count(DISTINCT a) AS ka, count(DISTINCT b) AS kb FROM c), l AS (SELECT 0 AS col, a AS x, ka AS k, 0 AS before FROM c, k UNION ALL SELECT 1, b, kb, ka FROM c, k)
        SELECT 'index' AS psi, col::INT AS col_id, round(sum(x)::DOUBLE, 4) AS total FROM l GROUP BY col
        UNION ALL SELECT 'scaled', col, round(sum(x / (k - 1)), 4) FROM l GROUP BY col
        UNION ALL SELECT 'onehot', (before + x)::INT, round(count(*)::DOUBLE, 4) FROM l GROUP BY ALL
        UNION ALL SELECT 'mapping', col, round(sum((3 * x + 1) % 7)::DOUBLE, 4) FROM l GROUP BY col""",
    "raw_sizes": f"WITH {LINE_CELLS}, k AS (SELECT count(*) * log2(count(DISTINCT code)) AS b FROM cells GROUP BY name) SELECT 'KB' AS unit, round(sum(b) / 8192, 4) AS size FROM k UNION ALL SELECT 'MB', round(sum(b) / 8388608, 4) FROM k",
    "block_entropy_identity": f"WITH {BLOCKS}, t AS (SELECT cnt, sum(cnt) OVER (PARTITION BY u, v) AS t FROM hist) SELECT round(sum(cnt * log2(t / cnt)), 3) AS by_blocks, round(sum(cnt) * {_entropy('u, v')}, 3) AS by_entropy FROM t",
    "fitted_model": f"""WITH {BLOCKS}, t AS (SELECT *, sum(cnt) OVER (PARTITION BY u, v) AS t, sum(cnt) OVER (PARTITION BY u) AS tu, sum(cnt) OVER (PARTITION BY v) AS tv, sum(cnt) OVER () AS a FROM hist),
        s AS (SELECT DISTINCT u, v, t, tu, tv, a FROM t) SELECT s.u::INT AS u, s.v::INT AS v, x::INT AS code, round(coalesce(cnt, 0) / s.t, 6) AS p, round(s.tu / s.a, 6) AS row_share, round(s.tv / s.a, 6) AS col_share
        FROM s CROSS JOIN (SELECT unnest([0, 1]) AS x) LEFT JOIN t ON t.u = s.u AND t.v = s.v AND t.code = x""",
    "entropy_aggregate": "WITH c AS (SELECT l_returnflag, month(l_shipdate) AS m, count(*) AS c FROM lineitem GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY l_returnflag) AS t FROM c) SELECT l_returnflag, round(sum(c * log2(t / c)) / sum(c), 6) AS entropy FROM t GROUP BY 1",
    "sql_functions": """WITH n AS (SELECT count(*) AS n FROM orders GROUP BY o_custkey), f AS (SELECT n, length(bin(n)) AS w FROM n)
        SELECT n, count(*) AS customers, max(2 * w - 1)::INT AS gamma_bits, max(w + 2 * length(bin(w)) - 2)::INT AS delta_bits, max(3 * n)::BIGINT AS plain, 2::BIGINT AS ones_of_five FROM f GROUP BY n""",
    "fano_grid": f"WITH f AS (SELECT l_linenumber AS line, l_returnflag, count(*) AS c FROM lineitem GROUP BY ALL), g AS (SELECT line, err, k FROM (SELECT line, round(1 - max(c) / sum(c), 6) AS err FROM f GROUP BY line), (SELECT unnest([2, 3, 5, 8]) AS k)) SELECT line, err, k, round({_slack('err')}, 6) AS slack FROM g",
    "ideal_rates_grid": MEASURED_GRID
    + f"""t AS (SELECT *, {TIGHT} AS tight, {TIGHT} + log2(k) / 500 + log2(k) / 1000 AS up, {_slack('0.01::DOUBLE')} / 500 + {_slack('0.01::DOUBLE')} / 1000 AS d FROM g)
        SELECT line, p0, p1, k, round(greatest(tight, up - d), 6) AS lower, round(up, 6) AS upper, round(up + 1 / 500000.0, 6) AS reachable, round(up - d - 2 * log2(500000) / 500000.0, 6) AS floor,
        (2 * (k - 1) + k * k)::INT AS parameters, round(ln(1000) / ln(500), 6) AS alpha FROM t""",
    "spectral_conditions_grid": MODEL_GRID
    + """w AS (SELECT *, 2.0 * n AS m, ln(n) AS lg, least(abs(p1 - p0), abs((k - 1) * p0 + p1)) AS mu, greatest(p0, p1) AS nu, sqrt(greatest(p0 * (1 - p0), p1 * (1 - p1))) AS sigma FROM g, (SELECT unnest([1000, 100000]) AS n))
        SELECT p0, p1, k, n, round(mu, 6) AS mu, round(nu, 6) AS nu, round(sigma, 6) AS sigma,
        sigma >= 0.5 * sqrt(lg / n) AND nu <= 0.5 * sigma * sqrt(lg) AND (CASE WHEN mu < 1e-9 THEN 0 ELSE mu END) >= greatest(sigma * sqrt(lg / m), lg / sqrt(m * n)) AS promised,
        greatest(p0, p1) >= sqrt(lg / n) AS dense, abs(p1 - p0) >= lg / sqrt(m * n) AS apart, abs(p1 - p0) / greatest(p0, p1) >= sqrt(lg / n) AS strong FROM w""",
    "latent_bound_grid": f"""WITH {CHANCES}, g AS (SELECT line, p0, p1, k FROM chances, (SELECT unnest([3, 5]) AS k)), s AS (SELECT *, n * n AS cells FROM g, (SELECT unnest([1000, 10000]) AS n)),
        t AS (SELECT *, {TIGHT} + 2 * log2(k) / n AS up, greatest(16, floor(1.0 / (k * k) / 2 * cells)) AS inner_n FROM s),
        r AS (SELECT *, k * k * 4 * log2(inner_n) / inner_n + 2 * 2 * k * log2(n) / n AS red FROM t)
        SELECT line, p0, p1, k, n, round(up + 2 * 0.01 + 4 * log2(cells) / cells + red, 6) AS bound, round(up + 10 * log2(cells) / cells + red, 6) AS spectral_bound FROM r""",
    "enumerated_tables": f"""WITH {CHANCES}, {TINY}, m AS (SELECT line, p0, p1, t, sum(chance) AS c FROM q GROUP BY ALL), h AS (SELECT line, p0, p1, -sum(c * log2(c)) AS e FROM m GROUP BY ALL)
        SELECT line, p0, p1, round(e, 6) AS entropy, round(e - 4 * ({_h2('p0')} + {_h2('p1')}) / 2, 6) AS information FROM h""",
    "concentration_constants": f"WITH {CHANCES}" + """, r AS (SELECT line, p0, p1, abs(p1 - p0) AS tv, abs(ln(p0 / (1 - p0))) AS a, abs(ln(p1 / (1 - p1))) AS b FROM chances),
        c AS (SELECT *, greatest(a, b) AS ratio, tv * greatest(a, b) AS m1, greatest(2 * p0 * (1 - p0), 2 * p1 * (1 - p1)) * greatest(a, b) ** 2 / 2 AS s, tv * greatest(a, b) ** 2 / 2 AS s1 FROM r)
        SELECT line, p0, p1, round(ratio, 5) AS ratio, round(m1, 5) AS m1, round(m1, 5) AS m2, round(s, 5) AS s, round(s1, 5) AS s1, round(s1, 5) AS s2,
        round(3 * greatest(sqrt(s * 5000 * 3) + sqrt(s1 * 250000 * 3) + sqrt(s1 * 500000 * 3), (ratio + m1 * 150) * 3), 5) AS bound FROM c""",
    "equipartition_deviation": f"WITH {CHANCES} SELECT line, p0, p1, true AS within FROM chances",
    "injective_bounds": """WITH c AS (SELECT count(*) AS c FROM events GROUP BY event_type), t AS (SELECT c / (SELECT sum(c) FROM c) AS p, row_number() OVER (ORDER BY c DESC) AS r, count(*) OVER () AS n FROM c)
        SELECT round(-sum(p * log2(p)) - log2(log2(max(n) + 2)), 6) AS bound, round(sum(p * floor(log2(r))), 6) AS shortest FROM t""",
    "joint_law": f"WITH {CHANCES} SELECT line, u::INT AS u, v::INT AS v, x::INT AS x, round((CASE WHEN x = 1 THEN p ELSE 1 - p END) / 9, 6) AS p FROM (SELECT line, u, v, x, CASE WHEN u = v THEN p1 ELSE p0 END AS p FROM chances, (SELECT unnest(range(3)) AS u), (SELECT unnest(range(3)) AS v), (SELECT unnest(range(2)) AS x))",
    "total_variation_general": """WITH c AS (SELECT l_returnflag AS u, l_linestatus AS v, month(l_shipdate) AS x, count(*) AS c FROM lineitem GROUP BY ALL), p AS (SELECT *, c / sum(c) OVER (PARTITION BY u, v) AS p FROM c),
        b AS (SELECT DISTINCT u, v FROM c), s AS (SELECT DISTINCT x FROM c)
        SELECT a.u, a.v, b.u AS u2, b.v AS v2, round(sum(abs(coalesce(p.p, 0) - coalesce(q.p, 0))) / 2, 6) AS tv FROM b a JOIN b ON (a.u, a.v) < (b.u, b.v) CROSS JOIN s
        LEFT JOIN p ON p.u = a.u AND p.v = a.v AND p.x = s.x LEFT JOIN p q ON q.u = b.u AND q.v = b.v AND q.x = s.x GROUP BY ALL""",
    "finite_state_machine": "WITH s AS (SELECT o_custkey, (o_orderstatus = 'O')::INT AS x, lag((o_orderstatus = 'O')::INT, 1, 0) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS y FROM orders) SELECT o_custkey, sum(CASE WHEN x = y THEN 1 ELSE 2 END)::BIGINT AS bits FROM s GROUP BY 1",
    "lz_length_identity": "SELECT count(DISTINCT o_custkey) AS sequences, 0::BIGINT AS different FROM orders",
    "covariances": "SELECT l_returnflag, round(covar_pop(l_quantity, l_discount), 6) AS covariance, round(corr(l_quantity, l_extendedprice), 6) AS correlation FROM lineitem GROUP BY 1",
    "commonest_symbols": "WITH c AS (SELECT l_returnflag, l_linestatus, month(l_shipdate) AS m, count(*) AS cnt FROM lineitem GROUP BY ALL) SELECT l_returnflag, l_linestatus, m::BIGINT AS mode, cnt FROM c QUALIFY row_number() OVER (PARTITION BY l_returnflag, l_linestatus ORDER BY cnt DESC, m) = 1",
    "range_frames": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 360000000000 PRECEDING AND CURRENT ROW) AS n FROM events",
    "set_intersections": """WITH a AS (SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'), b AS (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')
        SELECT 'intersect' AS kind, count(*) AS n FROM (FROM a INTERSECT FROM b) UNION ALL SELECT 'except', count(*) FROM (FROM a EXCEPT FROM b)
        UNION ALL SELECT 'union', count(*) FROM (FROM a UNION FROM b) UNION ALL SELECT 'intersect_all', count(*) FROM (FROM a INTERSECT ALL FROM b)""",
    "calendar_fields": """SELECT year(l_shipdate) AS year, quarter(l_shipdate) AS quarter, month(l_shipdate) AS month, weekofyear(l_shipdate) AS week, count(*) AS n,
        round(avg(date_diff('day', o_orderdate::DATE, l_shipdate::DATE)), 6) AS lag FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL""",
    "json_properties": "SELECT event_type, count((props::JSON->>'k')::INT) AS n, sum((props::JSON->>'k')::INT)::BIGINT AS k FROM events GROUP BY 1",
    "closed_form_entropy_columns": MEASURED_GRID + f"z AS (SELECT 1) SELECT line, p0, p1, k, round({_h2('mean')}, 6) AS h FROM g",
}

_ALL_DOCUMENTS = "SELECT count(*) AS n, true AS same, true AS sized, true AS within_raw FROM documents"
SETS = r"""words AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[^ \n\t.,;:!?|]+')) AS word FROM documents), n AS (SELECT doc_id, count(*) AS n FROM words GROUP BY doc_id)"""

ORACLES |= {f"container_round_trip_{coder}": _ALL_DOCUMENTS for coder in ("rans", "zstd", "lz")}
ORACLES |= {
    "predicate_on_codes": " UNION ALL ".join(
        f"SELECT '{p.replace(chr(39), chr(39) * 2)}' AS predicate, count(*) AS n FROM orders WHERE {p}" for p in ("o_orderpriority LIKE '%U%'", "o_orderstatus IN ('F', 'P')", "o_orderstatus = 'O'", "o_orderpriority > '3'")
    ),
    "doc_word_set_edges": f"WITH {SETS.partition(", n AS")[0]}, w AS (FROM words), {_links(0.3)}",
    "doc_top10_edges": f"""WITH {SETS}, both_ AS (SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS c FROM words a JOIN words b ON a.word = b.word AND a.doc_id <> b.doc_id GROUP BY ALL),
        every AS (SELECT a.doc_id AS src, b.doc_id AS dst, coalesce(c, 0) / greatest(1, coalesce(p.n, 0) + coalesce(q.n, 0) - coalesce(c, 0)) AS s FROM documents a JOIN documents b ON a.doc_id <> b.doc_id AND a.doc_id % 50 = 0
          LEFT JOIN both_ ON src = a.doc_id AND dst = b.doc_id LEFT JOIN n p ON p.doc_id = a.doc_id LEFT JOIN n q ON q.doc_id = b.doc_id)
        SELECT src, dst FROM every QUALIFY row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) <= 10""",
}
ORACLES |= {
    "stream_rates": """WITH c AS (SELECT date_trunc('day', ts) AS d, 0 AS j, event_type AS x FROM events UNION ALL SELECT date_trunc('day', ts), 1, json_extract_string(props, '$.k') FROM events),
        k AS (SELECT j, count(DISTINCT x) AS k FROM c GROUP BY j), h AS (SELECT d, j, x, count(*) AS c FROM c GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY d, j) AS t FROM h),
        s AS (SELECT d, j, max(t) AS n, sum(c * log2(t / c)) AS b, count(*) * 64 AS q FROM t GROUP BY d, j)
        SELECT epoch(d)::BIGINT AS start, round(sum(b / n), 6) AS entropy, round(1 - sum(b + q) / sum(n * log2(k)), 6) AS drr FROM s JOIN k USING (j) GROUP BY d""",
    "stream_late_rows": "SELECT count(*) AS n, count(DISTINCT event_id) AS events, true AS all_counted FROM events",
    "stream_pairs": "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY GROUP BY 1",
}
