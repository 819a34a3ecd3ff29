"""DuckDB SQL for the queries that SQL expresses: the same numbers by other means."""

from __future__ import annotations

LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
TEXT_COLUMNS = {"l_returnflag", "l_linestatus"}


def _number(c: str) -> str:
    return f"epoch_us({c})::DOUBLE" if c.endswith("date") else f"{c}::DOUBLE"


def _code_cells(columns: list[str], source: str, texts: set[str]) -> str:
    """``cells(col_id, name, code)`` of a table: one branch a column, dictionary or quartile by its distinct count."""
    parts = []
    for j, c in enumerate(columns):
        dictionary = f"SELECT {j} AS col_id, '{c}' AS name, 'C' AS kind, dense_rank() OVER (ORDER BY {c}) - 1 AS code FROM {source} WHERE (SELECT count(DISTINCT {c}) FROM {source}) <= 256"
        parts.append(dictionary)
        if c not in texts:
            parts.append(
                f"SELECT {j}, '{c}', 'Q', (x > q[1])::INT + (x > q[2])::INT + (x > q[3])::INT FROM (SELECT {_number(c)} AS x FROM {source}), "
                f"(SELECT quantile_cont({_number(c)}, [0.25, 0.5, 0.75]) AS q, count(DISTINCT {c}) AS d FROM {source}) WHERE d > 256"
            )
    return "cells AS (" + " UNION ALL ".join(parts) + ")"


LINE_CELLS = _code_cells(LINE, "lineitem", TEXT_COLUMNS)

WORDS = r"""
words AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[^ \n\t.,;:!?|]+')) AS word FROM documents),
top AS (SELECT word, count(*) AS df, row_number() OVER (ORDER BY count(*) DESC, word) - 1 AS col_id FROM words GROUP BY word ORDER BY df DESC, word LIMIT 200)"""

BLOCKS = (
    WORDS
    + """,
langs AS (SELECT doc_id, CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS u FROM documents),
ones AS (SELECT u, (col_id // 50)::INT AS v, count(*) AS c FROM words JOIN top USING (word) JOIN langs USING (doc_id) GROUP BY ALL),
sizes AS (SELECT u, v, count(*) * 50 AS t FROM langs, (SELECT unnest([0, 1, 2, 3]) AS v) GROUP BY ALL),
hist AS (SELECT * FROM (
  SELECT u, v, 1 AS code, coalesce(c, 0) AS cnt FROM sizes LEFT JOIN ones USING (u, v)
  UNION ALL SELECT u, v, 0, t - coalesce(c, 0) FROM sizes LEFT JOIN ones USING (u, v)) WHERE cnt > 0)"""
)


def _entropy(given: str) -> str:
    over = f"OVER (PARTITION BY {given})" if given else "OVER ()"
    keys = f"{given}, code" if given else "code"
    return f"(SELECT sum(c * log2(t / c)) / sum(c) FROM (SELECT c, sum(c) {over} AS t FROM (SELECT {keys}, sum(cnt) AS c FROM hist GROUP BY {keys})))"


def _h2(p: str) -> str:
    return f"(CASE WHEN {p} > 0 THEN -({p}) * log2({p}) ELSE 0 END + CASE WHEN {p} < 1 THEN -(1 - ({p})) * log2(1 - ({p})) ELSE 0 END)"


GRID = """grid AS (SELECT p0, p1, k, alpha FROM (SELECT unnest([0.05, 0.1, 0.3, 0.5]::DOUBLE[]) AS p0), (SELECT unnest([0.5, 0.7, 0.9]::DOUBLE[]) AS p1), (SELECT unnest([3, 5, 7]) AS k), (SELECT unnest([0.5, 1.0, 2.0]::DOUBLE[]) AS alpha)),
forms AS (SELECT *, (k - 1) / k * p0 + p1 / k AS mean FROM grid)"""
#: The same over the chances measured on the line items (``queries.measured_chances``).
CHANCES = "chances AS (SELECT l_linenumber AS line, round(avg((l_returnflag = 'R')::INT), 6) AS p0, round(avg((l_discount < 0.065)::INT), 6) AS p1 FROM lineitem GROUP BY 1)"
MEASURED = f"""{CHANCES}, grid AS (SELECT line, p0, p1, k, alpha FROM chances, (SELECT unnest([3, 5, 7]) AS k), (SELECT unnest([0.5, 1.0, 2.0]::DOUBLE[]) AS alpha)),
forms AS (SELECT *, (k - 1) / k * p0 + p1 / k AS mean FROM grid)"""
TIGHT = f"((k - 1) / k * {_h2('p0')} + {_h2('p1')} / k)"

STAR = """star AS (SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey)"""
INDICATED = ["p_brand", "p_type", "c_mktsegment", "o_orderpriority", "o_orderstatus"]
TRANSACTION = ["l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_returnflag", "l_shipdate", "o_custkey", "o_totalprice", "o_orderdate", "c_nationkey", "c_acctbal"]


def _variate(*parts: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 8))::BIGINT / 4294967296.0)"


PLANTED = "[[0.9, 0.1, 0.3, 0.5, 0.2, 0.7], [0.2, 0.8, 0.1, 0.4, 0.6, 0.3], [0.5, 0.3, 0.9, 0.1, 0.7, 0.2], [0.1, 0.6, 0.4, 0.9, 0.3, 0.5], [0.7, 0.2, 0.6, 0.3, 0.1, 0.9]]"



def _links(threshold: float) -> str:
    """Class of equal word sets in ``w(doc_id, word)`` and number of links of each document."""
    return f"""n AS (SELECT doc_id, count(*) AS n, list(word ORDER BY word) AS s FROM w GROUP BY doc_id), both_ AS (SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS c FROM w a JOIN w b ON a.word = b.word AND a.doc_id <> b.doc_id GROUP BY ALL),
        k AS (SELECT src, count(*) AS k FROM both_ JOIN n p ON p.doc_id = src JOIN n q ON q.doc_id = dst WHERE c >= {threshold}::DOUBLE * (p.n + q.n - c) GROUP BY src)
        SELECT doc_id, min(doc_id) OVER (PARTITION BY coalesce(s, [])) AS class_id, coalesce(k, 0) AS n_links FROM documents LEFT JOIN n USING (doc_id) LEFT JOIN k ON src = doc_id"""


ORACLES: dict[str, str] = {
    "profile_columns": " UNION ALL ".join(f"SELECT '{c}' AS col_name, CASE WHEN d <= 256 THEN d END AS n_distinct, CASE WHEN d <= 256 THEN 'C' ELSE '{'D' if c in TEXT_COLUMNS else 'Q'}' END AS kind FROM (SELECT count(DISTINCT {c}) AS d FROM lineitem)" for c in LINE),
    "codebook_lineitem": " UNION ALL ".join(
        [f"SELECT '{c}' AS col_name, 'C' AS kind, unnest(range(d))::INT AS code, NULL::DOUBLE AS cut_lo, NULL::DOUBLE AS cut_hi FROM (SELECT count(DISTINCT {c}) AS d FROM lineitem) WHERE d <= 256" for c in LINE]
        + [
            f"SELECT '{c}', 'Q', k, CASE WHEN k > 0 THEN round(q[k], 6) END, CASE WHEN k < 3 THEN round(q[k + 1], 6) END FROM (SELECT quantile_cont({_number(c)}, [0.25, 0.5, 0.75]) AS q, count(DISTINCT {c}) AS d FROM lineitem), (SELECT unnest([0, 1, 2, 3]) AS k) WHERE d > 256"
            for c in LINE
            if c not in TEXT_COLUMNS
        ]
    ),
    "quartile_codes_lineitem": f"WITH {LINE_CELLS} SELECT name AS col_name, code::INT AS code, count(*) AS cnt FROM cells WHERE kind = 'Q' GROUP BY ALL",
    "codes_histogram": f"WITH {LINE_CELLS} SELECT col_id, code::INT AS code, count(*) AS cnt FROM cells GROUP BY ALL",
    "raw_bits_per_column": f"WITH {LINE_CELLS} SELECT name AS col_name, count(DISTINCT code)::INT AS card, round(count(*) * log2(count(DISTINCT code)), 4) AS raw_bits FROM cells GROUP BY name",
    "raw_bits_common": f"WITH {LINE_CELLS}, cards AS (SELECT name, count(DISTINCT code) AS k, count(*) AS m FROM cells GROUP BY name) SELECT max(m) AS m, count(*)::INT AS n, round(max(m) * count(*) * log2(max(k)), 4) AS raw_bits FROM cards",
    "entropy_per_column": f"WITH {LINE_CELLS}, h AS (SELECT col_id, code, count(*) AS c FROM cells GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY col_id) AS t FROM h) SELECT col_id, round(sum(c * log2(t / c)) / sum(c), 6) AS entropy FROM t GROUP BY col_id",
    "entropy_table": f"WITH {LINE_CELLS}, h AS (SELECT code, count(*) AS c FROM cells GROUP BY ALL), t AS (SELECT *, sum(c) OVER () AS t FROM h) SELECT round(sum(c * log2(t / c)) / sum(c), 6) AS entropy FROM t",
    "ans_baseline_column": f"WITH {LINE_CELLS}, h AS (SELECT col_id, code, count(*) AS c FROM cells GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY col_id) AS t FROM h) SELECT col_id, sum(c)::BIGINT AS n, round(sum(c * log2(t / c)), 4) AS code_bits, count(*) * 64 AS count_bits FROM t GROUP BY col_id",
    "ans_baseline_table": f"WITH {LINE_CELLS}, h AS (SELECT code, count(*) AS c FROM cells GROUP BY ALL), t AS (SELECT *, sum(c) OVER () AS t FROM h) SELECT sum(c)::BIGINT AS n, round(sum(c * log2(t / c)), 4) AS code_bits, count(*) * 64 AS count_bits FROM t",
    "arithmetic_size_bound": f"WITH {LINE_CELLS}, h AS (SELECT col_id, code, count(*) AS c FROM cells GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY col_id) AS t FROM h) SELECT col_id, round(sum(c * log2(t / c)) + 1 + sum(2 * (length(bin(c)) - 1) + 1), 4) AS size, round(sum(c * log2(t / c)) + 2 * count(*) * log2(max(t)), 4) AS bound FROM t GROUP BY col_id",
    "block_histogram_given_labels": f"WITH {BLOCKS} SELECT u, v, code, cnt FROM hist",
    "entropy_cube_given_labels": f"""WITH {BLOCKS}, cube AS (SELECT u, v, code, sum(cnt) AS c, grouping(u) * 2 + grouping(v) AS gid FROM hist GROUP BY GROUPING SETS ((u, v, code), (u, code), (v, code), (code))),
        tot AS (SELECT *, sum(c) OVER (PARTITION BY gid, u, v) AS t FROM cube) SELECT u, v, gid::INT AS gid, sum(c)::BIGINT AS n, round(sum(c * log2(t / c)) / sum(c), 6) AS entropy FROM tot GROUP BY u, v, gid""",
    "plugin_entropies": f"WITH {BLOCKS} SELECT round({_entropy('')}, 6) AS h_x, round({_entropy('u')}, 6) AS h_x_u, round({_entropy('v')}, 6) AS h_x_v, round({_entropy('u, v')}, 6) AS h_x_uv",
    "entropy_upper_with_labels": f"WITH {BLOCKS}, l AS (SELECT count(*) AS c FROM langs GROUP BY u), m AS (SELECT sum(c) AS m, sum(c * log2((SELECT sum(c) FROM l) / c)) / sum(c) AS hu FROM l) SELECT round({_entropy('u, v')} + hu / 200 + 2.0 / m, 6) AS h_plus FROM m",
    "ans_size_blocks_given_labels": f"WITH {BLOCKS}, t AS (SELECT *, sum(cnt) OVER (PARTITION BY u, v) AS t FROM hist) SELECT u, v, sum(cnt)::BIGINT AS n, round(sum(cnt * log2(t / cnt)), 4) AS code_bits, count(*) * 64 AS count_bits FROM t GROUP BY u, v",
    "drr_given_labels": f"""WITH {BLOCKS}, t AS (SELECT *, sum(cnt) OVER (PARTITION BY u, v) AS t FROM hist), b AS (SELECT sum(cnt * log2(t / cnt)) + count(*) * 64 AS b FROM t),
        l AS (SELECT count(*) AS c FROM langs GROUP BY u), m AS (SELECT sum(c) AS m, sum(c * log2((SELECT sum(c) FROM l) / c)) + count(*) * 64 AS l FROM l)
        SELECT round(1 - (b + l + 18 * ceil(log2(m * 200 + 1)) + 400 + 256) / (m * 200.0), 6) AS drr FROM b, m""",
    "fano_and_break_even": f"WITH {BLOCKS}, l AS (SELECT count(*) AS c FROM langs GROUP BY u), m AS (SELECT sum(c * log2((SELECT sum(c) FROM l) / c)) / sum(c) AS hu FROM l) SELECT round(hu / 200, 6) AS cost, round({_entropy('v')} - {_entropy('u, v')}, 6) AS gain, hu / 200 < {_entropy('v')} - {_entropy('u, v')} AS pays FROM m",
    "ngram_entropy": """WITH c AS (SELECT dense_rank() OVER (ORDER BY l_linenumber) - 1 AS a, dense_rank() OVER (ORDER BY l_quantity) - 1 AS b, dense_rank() OVER (ORDER BY l_returnflag) - 1 AS d FROM lineitem),
        g AS (SELECT a::VARCHAR || ',' || b AS gram FROM c UNION ALL SELECT b::VARCHAR || ',' || d FROM c), h AS (SELECT gram, count(*) AS c FROM g GROUP BY gram), t AS (SELECT c, sum(c) OVER () AS t FROM h)
        SELECT round(sum(c * log2(t / c)) / sum(c), 6) AS entropy, round(sum(c * log2(t / c)) / sum(c) / 2, 6) AS per_symbol FROM t""",
    "block_moments": f"WITH {BLOCKS}, p AS (SELECT u, v, sum(cnt) FILTER (code = 1) / sum(cnt) AS p FROM hist GROUP BY u, v) SELECT u, v, round(coalesce(p, 0), 6) AS mean, round(coalesce(p, 0) * (1 - coalesce(p, 0)), 6) AS variance FROM p",
    "block_distances": f"WITH {BLOCKS}, p AS (SELECT u, v, coalesce(sum(cnt) FILTER (code = 1), 0) / sum(cnt) AS p FROM hist GROUP BY u, v) SELECT a.u, a.v, b.u AS u2, b.v AS v2, round(abs(a.p - b.p), 6) AS tv FROM p a JOIN p b ON (a.u, a.v) < (b.u, b.v)",
    "elias_gamma_sizes": "WITH l AS (SELECT count(*) AS x FROM lineitem GROUP BY l_orderkey), b AS (SELECT x, floor(log2(x + 0.5))::BIGINT AS f FROM l) SELECT x, count(*) AS orders, sum(2 * f + 1)::BIGINT AS gamma_bits, sum(f + 2 * floor(log2(f + 1.5))::BIGINT + 1)::BIGINT AS delta_bits FROM b GROUP BY x",
    "plain_sizes": f"WITH {LINE_CELLS} SELECT name AS col_name, (count(*) * ceil(log2(count(DISTINCT code))))::BIGINT AS plain_bits FROM cells GROUP BY name",
    "label_error_permutation": """WITH c AS (SELECT CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS t, (n_chars % 4)::INT AS e, count(*) AS n FROM documents GROUP BY ALL),
        r AS (SELECT unnest([0, 1, 2, 3]) AS x), perm AS (SELECT row_number() OVER () AS id, [a.x, b.x, c2.x, d.x] AS p FROM r a, r b, r c2, r d WHERE len(list_distinct([a.x, b.x, c2.x, d.x])) = 4),
        s AS (SELECT id, coalesce(sum(n), 0) AS hit FROM perm LEFT JOIN c ON p[t + 1] = e GROUP BY id) SELECT round(1 - max(hit) / (SELECT sum(n) FROM c), 6) AS err FROM s""",
    "sbm_cells_md5": f"""WITH i AS (SELECT unnest(range(64)) AS i), rows AS (SELECT i, ({_variate("'42'", "'u'", "i::VARCHAR")} >= 1 / 3.0)::INT + ({_variate("'42'", "'u'", "i::VARCHAR")} >= 2 / 3.0)::INT AS u FROM i),
        cols AS (SELECT i AS j, ({_variate("'42'", "'v'", "i::VARCHAR")} >= 1 / 3.0)::INT + ({_variate("'42'", "'v'", "i::VARCHAR")} >= 2 / 3.0)::INT AS v FROM i)
        SELECT u, v, ({_variate("'42'", "i::VARCHAR", "j::VARCHAR")} >= CASE WHEN u = v THEN 1 - 0.9::DOUBLE ELSE 0.9::DOUBLE END)::INT AS code, count(*) AS cnt FROM rows, cols GROUP BY ALL""",
    "planted_counts": f"""WITH r AS (SELECT c_custkey, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS u FROM customer), c AS (SELECT p_partkey, dense_rank() OVER (ORDER BY p_type) - 1 AS v FROM part)
        SELECT u::INT AS u, v::INT AS v, ({_variate("'42'", "c_custkey::VARCHAR", "p_partkey::VARCHAR")} < ({PLANTED})[u + 1][v + 1])::INT AS code, count(*) AS cnt FROM r, c GROUP BY ALL""",
    "iid_draws": f"SELECT ({_variate("'7'", "i::VARCHAR", "'0'")} >= 0.7::DOUBLE)::INT + ({_variate("'7'", "i::VARCHAR", "'0'")} >= 0.7::DOUBLE + 0.2::DOUBLE)::INT AS code, count(*) AS cnt FROM (SELECT o_orderkey AS i FROM orders) GROUP BY ALL",
    "sbm_closed_forms_grid": f"WITH {GRID} SELECT p0, p1, k, alpha, round({TIGHT}, 6) AS opt, round({_h2('mean')}, 6) AS fs, round(least({_h2('mean')}, (1 + alpha) / alpha * {TIGHT}), 6) AS lz FROM forms",
    "lz_regime_grid": f"""WITH {MEASURED}, e AS (SELECT *, {_h2("mean")} AS wide, {TIGHT} AS tight FROM forms), s AS (SELECT *, CASE WHEN wide - tight > 1e-12 THEN tight / (wide - tight) END AS star FROM e)
        SELECT line, p0, p1, k, alpha, round(least(wide, (1 + alpha) / alpha * tight), 6) AS rate, round(star, 4) AS alpha_star, CASE WHEN alpha > star THEN 'aligned' ELSE 'scattered' END AS regime FROM s""",
    "finite_state_bound_grid": f"""WITH {MEASURED}, g AS (SELECT DISTINCT line, p0, p1, k, mean, states, n FROM forms, (SELECT unnest([2, 16, 256]) AS states), (SELECT unnest([1000, 100000]) AS n))
        SELECT line, p0, p1, k, states, n, round({_h2("mean")} - 10 * sqrt(ln(states) / (n * ln(2))) * ln(n * ln(states)), 6) AS bound, log2(states) <= n / 9.0 AS valid FROM g""",
    "redundancy_bounds_grid": "SELECT col_name, card::INT AS card, n, round(2 * card / log2(card) * log2(n) / n, 8) AS ac, round(2 * card * log2(n) / n, 8) AS ans FROM ("
    + " UNION ALL ".join(f"SELECT '{c}' AS col_name, count(DISTINCT {c}) AS card, count({c}) AS n FROM lineitem" for c in ("l_linenumber", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus")) + ")",
    "topk_words": f"WITH {WORDS} SELECT col_id::INT AS col_id, word, df FROM top",
    "word_presence_sums": f"WITH {WORDS}, c AS (SELECT doc_id, count(*) AS n FROM words JOIN top USING (word) GROUP BY doc_id) SELECT doc_id, coalesce(n, 0) AS words FROM documents LEFT JOIN c USING (doc_id)",
    "doc_jaccard_edges": f"WITH {WORDS}, w AS (SELECT doc_id, word FROM words JOIN top USING (word)), {_links(0.4)}",
    "supplier_degrees": "WITH s AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem), p AS (SELECT a.l_suppkey AS a, b.l_suppkey AS b FROM s a JOIN s b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey <> b.l_suppkey GROUP BY ALL HAVING count(*) >= 29), d AS (SELECT a, count(*) AS n FROM p GROUP BY a) SELECT s_suppkey - (SELECT min(s_suppkey) FROM supplier) AS row_id, coalesce(n, 0) AS degree FROM supplier LEFT JOIN d ON a = s_suppkey",
    "onehot_55": "WITH " + STAR + " " + " UNION ALL ".join(f"SELECT 'is_{c}_' || (dense_rank() OVER (ORDER BY {c}) - 1) AS col_name, count(*) AS ones FROM star GROUP BY {c}" for c in INDICATED),
    "ratings_101": f"WITH {STAR}, c AS (SELECT c_custkey, p_brand, least(3, (p_size - 1) // 13) AS band, round(avg(l_quantity)) AS q FROM star GROUP BY ALL) SELECT c_custkey, count(*) AS n_rated, round(sum(q) + (100 - count(*)) * 99.0, 2) AS total FROM c GROUP BY c_custkey",
    "wide_star_codes": f"WITH {STAR}, {_code_cells(TRANSACTION, 'star', {'l_returnflag'})} SELECT col_id, code::INT AS code, count(*) AS cnt FROM cells GROUP BY ALL",
    "row_ids_by_order": "SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS row_id, o_orderkey FROM orders",
    "shuffled_order": "WITH r AS (SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS r, o_orderkey FROM orders) SELECT row_number() OVER (ORDER BY md5('42|' || r)) - 1 AS row_id, o_orderkey FROM r",
    "star_joins_inner": f"WITH {STAR} SELECT c_mktsegment, p_type, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM star GROUP BY ALL",
    "star_joins_left": "SELECT c_nationkey, count(*) AS n, count(o_orderkey) AS with_order FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_nationkey",
    "star_joins_semi_anti": "SELECT 'semi' AS kind, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) UNION ALL SELECT 'anti', count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "star_joins_full": "SELECT lang, quality, count(*) AS n FROM documents FULL JOIN labels USING (doc_id) GROUP BY ALL",
    "range_lookup": "SELECT (x > q[1])::INT + (x > q[2])::INT + (x > q[3])::INT AS code, count(*) AS cnt FROM (SELECT l_extendedprice AS x FROM lineitem), (SELECT quantile_cont(l_extendedprice, [0.25, 0.5, 0.75]) AS q FROM lineitem) GROUP BY ALL",
    "grouping_sets_sizes": "SELECT l_returnflag, l_linestatus, count(*) AS n, (grouping(l_returnflag) * 2 + grouping(l_linestatus))::INT AS gid FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "set_ops_roundtrip": "SELECT count(*) AS n, 0::BIGINT AS lost, 0::BIGINT AS added FROM lineitem",
    "running_offsets": "SELECT o_custkey, o_orderkey, round(coalesce(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0), 2) AS before FROM orders",
    "recurrence_times": "WITH s AS (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events), w AS (SELECT event_type, pos - lag(pos) OVER (PARTITION BY user_id, event_type ORDER BY pos) AS wait FROM s) SELECT event_type, count(*) AS n, round(avg(wait), 6) AS mean_wait, max(wait) AS max_wait FROM w WHERE wait IS NOT NULL GROUP BY event_type",
    "events_windows": "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, count(*) AS n, round(sum(value), 2) AS value FROM events GROUP BY ALL",
    "session_windows": "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g), n AS (SELECT user_id, s, count(*) AS n FROM s GROUP BY ALL) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM n GROUP BY user_id",
    "stream_batch_equality": "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, count(*) AS n, sum((event_type NOT IN ('purchase', 'error'))::INT)::BIGINT AS unseen FROM events GROUP BY ALL",
    "lz_phrases_small": """WITH RECURSIVE s AS (SELECT o_custkey, string_agg(left(o_orderpriority, 1), '' ORDER BY o_orderkey) AS s FROM orders GROUP BY o_custkey),
        p AS (SELECT o_custkey, s, -1 AS phrase_no, 0 AS k, 0 AS len, 0 AS ptr FROM s
          UNION ALL SELECT o_custkey, s, phrase_no + 1, k + greatest(best, 1), greatest(best, 1), CASE WHEN best > 0 THEN strpos(s, substr(s, k + 1, best)) ELSE -(substr(s, k + 1, 1)::INT) END
          FROM (SELECT *, coalesce(list_max(list_filter(range(1, length(s) - k + 1), lambda x: contains(substr(s, 1, (k + x - 1)::INT), substr(s, k + 1, x::INT)))), 0)::INT AS best FROM p WHERE k < length(s)))
        SELECT o_custkey, phrase_no::INT AS phrase_no, (k - len + 1)::BIGINT AS start, len::BIGINT AS length, ptr::BIGINT AS pointer FROM p WHERE phrase_no >= 0""",
    "asof_purchases": "SELECT e.event_id, round(b.value, 4) AS last_value FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY ALL) b ON e.user_id = b.user_id AND e.ts >= b.ts",
    "interval_join": "WITH v AS (SELECT i::INT AS version, 1704067200000000 + i * 43200000000 AS lo, 1704067200000000 + i * 43200000000 + (i % 5 + 1) * 10800000000 AS hi FROM (SELECT unnest(range(60)) AS i)) SELECT version, count(*) AS n FROM events JOIN v ON epoch_us(ts) >= lo AND epoch_us(ts) < hi GROUP BY version",
    "top_values_per_group": "SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey)::INT AS rank FROM orders QUALIFY rank <= 3",
    "planted_recovery": "SELECT count(*) AS n, 0.0::DOUBLE AS err FROM customer GROUP BY c_mktsegment",
}


def oracle_sql() -> dict[str, str]:
    from blockpress import oracles_measures

    return ORACLES | oracles_measures.ORACLES
