"""The queries restated in DuckDB SQL: common tables are chained, three k-means rounds unrolled."""

from __future__ import annotations

ALPHAS = "[0.0, 0.001, 0.002, 0.005, 0.01, 0.02, 0.05, 0.1]"
ITERS = 3

ELEM = ["elem AS MATERIALIZED (SELECT vec_id AS id, unnest(range(64)) AS d, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings)"]
VECS = ["vecs AS MATERIALIZED (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)"]
PAIRS = ["pairs AS MATERIALIZED (SELECT q.id AS query_id, x.id AS vec_id, q.v AS q, x.v AS x FROM vecs q, vecs x WHERE q.id % 5 = 0 AND x.id % 5 <> 0)"]


def sql(parts: list[str], select: str) -> str:
    return "WITH " + ",\n".join(parts) + "\n" + select


def assigned(name: str, rows: str, books: str) -> str:
    """(id, m, i): the nearest centroid of each subvector, the lowest index on ties."""
    return f"""{name} AS MATERIALIZED (SELECT id, m, i FROM (
  SELECT t.id, c.m, c.i, row_number() OVER (PARTITION BY t.id, c.m ORDER BY sum((t.x - c.c) * (t.x - c.c)), c.i) AS rn
  FROM {rows} t JOIN {books} c ON t.d = c.d GROUP BY t.id, c.m, c.i) WHERE rn = 1)"""


def books(m: int, k: int, iters: int = ITERS, p: str = "") -> list[str]:
    """Codebooks {p}c0 .. {p}c<iters> of (m, i, d, c) on the rows that are no queries."""
    w = 64 // m
    out = []
    if not p:
        out += [*ELEM, "t AS MATERIALIZED (SELECT * FROM elem WHERE id % 5 <> 0)"]
    out.append(f"{p}c0 AS MATERIALIZED (SELECT t.d // {w} AS m, r.i, t.d, t.x AS c FROM t JOIN (SELECT id, row_number() OVER (ORDER BY id) - 1 AS i FROM (SELECT DISTINCT id FROM t)) r ON t.id = r.id WHERE r.i < {k})")
    for n in range(iters):
        out.append(assigned(f"{p}a{n}", "t", f"{p}c{n}"))
        out.append(f"{p}c{n + 1} AS MATERIALIZED (SELECT c.m, c.i, c.d, coalesce(a.x, c.c) AS c FROM {p}c{n} c LEFT JOIN (SELECT a.i, t.d, avg(t.x) AS x FROM t JOIN {p}a{n} a ON t.id = a.id AND a.m = t.d // {w} GROUP BY a.i, t.d) a ON a.i = c.i AND a.d = c.d)")
    return out


def model(m: int, k: int) -> list[str]:
    return [*books(m, k), assigned("codes", "elem", f"c{ITERS}")]


def table_of(name: str, where: str, metric: str, cb: str = f"c{ITERS}") -> str:
    term = "q.x * c.c" if metric == "dot" else "(q.x - c.c) * (q.x - c.c)"
    return f"{name} AS MATERIALIZED (SELECT q.id AS query_id, c.m, c.i, sum({term}) AS y FROM elem q JOIN {cb} c ON q.d = c.d WHERE {where} GROUP BY q.id, c.m, c.i)"


#: About 1,000 training vectors by md5 of the id, all of fewer.
SAMPLE = "q.id % 5 <> 0 AND CAST('0x' || substr(md5(CAST(q.id AS VARCHAR)), 1, 8) AS BIGINT) * (SELECT count(DISTINCT id) FROM t) < 1000 * 4294967296"


def quantizer(metric: str) -> list[str]:
    """fy: sampled entries; cut: (g, alpha, m, lo, scale); loss: by alpha; best: the chosen row of loss."""
    return [
        table_of("fy", SAMPLE, metric),
        f"low AS MATERIALIZED (SELECT m, unnest(range(8)) AS g, unnest({ALPHAS}) AS alpha, unnest(quantile_cont(y, {ALPHAS})) AS lo FROM fy GROUP BY m)",
        f"span AS MATERIALIZED (SELECT g, quantile_cont(y - lo, list_transform({ALPHAS}, lambda a: 1 - a))[g + 1] AS s FROM fy JOIN low USING (m) GROUP BY g)",
        "cut AS MATERIALIZED (SELECT low.g, alpha, m, lo, CASE WHEN s > 0 THEN 255 / s ELSE 1.0 END AS scale FROM low JOIN span USING (g))",
        "loss AS MATERIALIZED (SELECT alpha, max(scale) AS scale, avg(power(greatest(0, least(255, floor(round(scale * (y - lo), 9)))) / scale + lo - y, 2)) AS loss FROM fy JOIN cut USING (m) GROUP BY alpha)",
        "best AS MATERIALIZED (SELECT * FROM loss ORDER BY loss, alpha LIMIT 1)",
        "tq AS MATERIALIZED (SELECT m, lo, scale FROM cut WHERE alpha = (SELECT alpha FROM best))",
        "bias AS MATERIALIZED (SELECT sum(lo) AS b, max(scale) AS a FROM tq)",
    ]


def byte_tables(metric: str) -> list[str]:
    return [table_of("qy", "q.id % 5 = 0", metric), "bt AS MATERIALIZED (SELECT query_id, m, i, CAST(greatest(0, least(255, floor(round(scale * (y - lo), 9)))) AS INTEGER) AS b FROM qy JOIN tq USING (m))"]


def scan(table: str, column: str) -> str:
    return f"scan AS MATERIALIZED (SELECT b.query_id, c.id AS vec_id, sum(b.{column}) AS score FROM codes c JOIN {table} b ON c.m = b.m AND c.i = b.i WHERE c.id % 5 <> 0 GROUP BY b.query_id, c.id)"


def ranked(source: str, k: int, direction: str = "") -> str:
    return f"SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score {direction}, vec_id) AS INTEGER) AS rnk, vec_id, score FROM {source} QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY score {direction}, vec_id) <= {k}"


def btq(m: int, metric: str = "sql2") -> list[str]:
    return [*model(m, 16), *quantizer(metric), *byte_tables(metric), scan("bt", "b")]


def real_tables(m: int, k: int, metric: str = "sql2") -> list[str]:
    return [*model(m, k), table_of("qy", "q.id % 5 = 0", metric), scan("qy", "y")]


TRUE_SQ = "list_sum(list_transform(list_zip(q, x), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"
EXACT = [*VECS, *PAIRS, f"exact AS MATERIALIZED (SELECT query_id, vec_id, {TRUE_SQ} AS score FROM pairs)"]
CODE_ROWS = "SELECT id AS vec_id, CAST(m AS INTEGER) AS m, CAST(i AS INTEGER) AS code FROM codes"
R6 = "SELECT query_id, rnk, vec_id, round(score, 6) AS score FROM ({})"


def metric_sql(term: str, outer: str = "{}") -> str:
    total = outer.format(f"list_sum(list_transform(list_zip(q, x), lambda p: {term}))")
    return sql([*VECS, *PAIRS], f"SELECT query_id, vec_id, round({total}, 6) AS value FROM pairs")


def recall(parts: list[str]) -> str:
    top = ranked("scan", 100)
    return sql(
        [*parts, *EXACT, f"nn AS ({ranked('exact', 1)})", f"top AS ({top})"],
        "SELECT CAST(r AS INTEGER) AS r, round((SELECT count(*) FROM nn JOIN top USING (query_id, vec_id) WHERE top.rnk <= r) / (SELECT count(*) FROM vecs WHERE id % 5 = 0)::DOUBLE, 6) AS recall FROM (SELECT unnest([1, 2, 5, 10, 20, 50, 100]) AS r)",
    )


def kmeans(iters: int) -> str:
    return sql([*books(16, 16, iters), assigned("fin", "t", f"c{iters}")], f"SELECT CAST(c.m AS INTEGER) AS m, CAST(c.i AS INTEGER) AS i, CAST(c.d AS INTEGER) AS d, round(c.c, 6) AS value, CAST(coalesce(n.n, 0) AS BIGINT) AS n FROM c{iters} c LEFT JOIN (SELECT m, i, count(*) AS n FROM fin GROUP BY m, i) n ON c.m = n.m AND c.i = n.i")


RECON = [*model(16, 16), f"recon AS MATERIALIZED (SELECT k.id, c.d, c.c AS y FROM codes k JOIN c{ITERS} c ON k.m = c.m AND k.i = c.i)"]
APPROX_L2 = "sqrt(greatest(0, score / a + b))"
HAM = [
    *ELEM,
    "proj AS MATERIALIZED (SELECT b, d, 1 - 2 * (CAST('0x' || substr(md5(b || ':' || d), 1, 1) AS INTEGER) & 1) AS s FROM (SELECT unnest(range(64)) AS b), (SELECT unnest(range(64)) AS d))",
    "bits AS MATERIALIZED (SELECT id, b, round(sum(x * s), 9) > 0 AS one FROM elem JOIN proj USING (d) GROUP BY id, b)",
    "halves AS MATERIALIZED (SELECT id, CAST(b // 32 AS INTEGER) AS half, CAST(sum(CASE WHEN one THEN 1::BIGINT << (b % 32)::INTEGER ELSE 0 END) AS BIGINT) AS bits FROM bits GROUP BY id, b // 32)",
]
WINDOW_FEATURES = """CAST(count(*) AS BIGINT) AS n, [count(*) FILTER (event_type = 'click'), count(*) FILTER (event_type = 'error'), count(*) FILTER (event_type = 'purchase'), count(*) FILTER (event_type = 'signup'), count(*) FILTER (event_type = 'view')]::DOUBLE[]
 || [coalesce(sum(value) FILTER (event_type = 'click'), 0), coalesce(sum(value) FILTER (event_type = 'error'), 0), coalesce(sum(value) FILTER (event_type = 'purchase'), 0), coalesce(sum(value) FILTER (event_type = 'signup'), 0), coalesce(sum(value) FILTER (event_type = 'view'), 0)]
 || [coalesce(avg(CAST(json_extract_string(props, '$.k') AS DOUBLE)), 0)] AS vec"""
EVENT_ROWS = "SELECT user_id, strftime(s, '%Y-%m-%d %H:%M:%S.%f') AS start_at, strftime(e, '%Y-%m-%d %H:%M:%S.%f') AS end_at, n, CAST(unnest(range(11)) AS INTEGER) AS d, round(unnest(vec), 6) AS v FROM w"

ORACLES: dict[str, str] = {
    "metric_l1": metric_sql("abs(p[1] - p[2])"),
    "metric_l2": metric_sql("(p[1] - p[2]) * (p[1] - p[2])", "sqrt({})"),
    "metric_lp3": metric_sql("power(abs(p[1] - p[2]), 3)", "power({}, 1.0 / 3)"),
    "metric_dot": metric_sql("p[1] * p[2]"),
    "metric_cosine": sql([*VECS, *PAIRS], "SELECT query_id, vec_id, round(list_inner_product(q, x) / sqrt(list_inner_product(q, q)) / sqrt(list_inner_product(x, x)), 6) AS value FROM pairs"),
    "subspace_split": sql(ELEM, "SELECT id AS vec_id, CAST(d // 4 AS INTEGER) AS m, CAST(d AS INTEGER) AS d, round(x, 6) AS v FROM elem"),
    "vq_codes": sql(model(1, 16), CODE_ROWS),
    "kmeans_iter0": kmeans(0),
    "kmeans_iter1": kmeans(1),
    "kmeans_iter3": kmeans(3),
    "btq_codes_8": sql(model(16, 16), CODE_ROWS),
    "btq_codes_16": sql(model(32, 16), CODE_ROWS),
    "btq_codes_32": sql(model(64, 16), CODE_ROWS),
    "pq_codes": sql(model(8, 256), CODE_ROWS),
    "pack4": sql(model(16, 16), "SELECT id AS vec_id, CAST(m // 2 AS INTEGER) AS byte_ix, CAST(sum(CASE WHEN m % 2 = 0 THEN i ELSE 16 * i END) AS INTEGER) AS byte_val FROM codes GROUP BY id, m // 2"),
    "unpack4": sql(model(16, 16), CODE_ROWS),
    "query_tables_l2": sql([*books(16, 16), table_of("qy", "q.id % 5 = 0", "sql2")], "SELECT query_id, CAST(m AS INTEGER) AS m, CAST(i AS INTEGER) AS i, round(y, 6) AS y FROM qy"),
    "query_tables_dot": sql([*books(16, 16), table_of("qy", "q.id % 5 = 0", "dot")], "SELECT query_id, CAST(m AS INTEGER) AS m, CAST(i AS INTEGER) AS i, round(y, 6) AS y FROM qy"),
    "pq_scan_topk": sql(real_tables(8, 256), R6.format(ranked("scan", 10))),
    "btqf_scan_topk": sql(real_tables(16, 16), R6.format(ranked("scan", 10))),
    "btq_scan_topk": sql(btq(16), "SELECT query_id, rnk, vec_id, CAST(score AS BIGINT) AS score FROM (" + ranked("scan", 10) + ")"),
    "table_quantiles": sql([*books(16, 16), table_of("fy", SAMPLE, "sql2")], f"SELECT CAST(m AS INTEGER) AS m, alpha, round(lo, 6) AS lo, round(hi, 6) AS hi FROM (SELECT m, unnest({ALPHAS})::DOUBLE AS alpha, unnest(quantile_cont(y, {ALPHAS})) AS lo, unnest(quantile_cont(y, list_transform({ALPHAS}, lambda a: 1 - a))) AS hi FROM fy GROUP BY m)"),
    "alpha_grid_loss": sql([*books(16, 16), *quantizer("sql2")], "SELECT alpha::DOUBLE AS alpha, round(scale, 6) AS scale, round(loss, 8) AS loss FROM loss"),
    "alpha_best": sql([*books(16, 16), *quantizer("sql2")], "SELECT alpha::DOUBLE AS alpha, round(scale, 6) AS scale, round(loss, 8) AS loss FROM best"),
    "byte_tables": sql([*books(16, 16), *quantizer("sql2"), *byte_tables("sql2")], "SELECT query_id, CAST(m AS INTEGER) AS m, CAST(i AS INTEGER) AS i, b FROM bt"),
    "dequant_distance": sql(btq(16), f"SELECT query_id, vec_id, round({APPROX_L2}, 6) AS value FROM scan, bias"),
    "reconstruct": sql(RECON, "SELECT id AS vec_id, CAST(d AS INTEGER) AS d, round(y, 6) AS value FROM recon"),
    "recon_mse": sql(RECON, "SELECT CAST(count(*) AS BIGINT) AS n, round(avg(e), 6) AS value FROM (SELECT id, sum((x - y) * (x - y)) AS e FROM recon JOIN elem USING (id, d) GROUP BY id)"),
    "recall_curve_btq": recall(btq(16)),
    "recall_curve_btqf": recall(real_tables(16, 16)),
    "recall_curve_pq": recall(real_tables(8, 256)),
    "corr_dot": sql([*btq(16, "dot"), *VECS, *PAIRS], "SELECT CAST(count(*) AS BIGINT) AS n, round(corr(list_inner_product(q, x), score / a + b), 6) AS value FROM scan JOIN pairs USING (query_id, vec_id), bias"),
    "corr_l2": sql([*btq(16), *EXACT], f"SELECT CAST(count(*) AS BIGINT) AS n, round(corr(sqrt(e.score), sqrt(greatest(0, s.score / a + b))), 6) AS value FROM scan s JOIN exact e USING (query_id, vec_id), bias"),
    "loss_mse": sql([*btq(16), *EXACT], "SELECT CAST(count(*) AS BIGINT) AS n, round(avg(power(sqrt(e.score) - sqrt(greatest(0, s.score / a + b)), 2)), 6) AS value FROM scan s JOIN exact e USING (query_id, vec_id), bias"),
    "compression_ratio": "WITH v AS (SELECT 'v_embed' AS view, count(vec_id) AS n, sum(len(embedding)) AS floats FROM embeddings UNION ALL SELECT 'v_walk', sum(n), 128 * sum(n) FROM (SELECT greatest(count(event_id) - 127, 0) AS n FROM events GROUP BY event_type) UNION ALL SELECT 'v_text512', count(doc_id), 512 * count(doc_id) FROM documents UNION ALL SELECT 'v_text784', count(doc_id), 784 * count(doc_id) FROM documents) SELECT view, CAST(bytes AS INTEGER) AS bytes, CAST(4 * floats AS DOUBLE) / CAST(n * bytes AS DOUBLE) AS ratio FROM v, (VALUES (8), (16), (32)) b(bytes)",
    "exact_nn": sql(EXACT, "SELECT query_id, rnk, vec_id, round(sqrt(score), 6) AS score FROM (" + ranked("exact", 10) + ")"),
    "exact_mips": "",
    "rerank_topk": sql([*btq(16), *EXACT, f"cand AS ({ranked('scan', 50)})", "cands AS (SELECT e.query_id, e.vec_id, e.score FROM exact e JOIN cand c USING (query_id, vec_id))"], R6.format(ranked("cands", 10))),
    "hamming_codes": sql(HAM, "SELECT id AS vec_id, half, bits FROM halves"),
    "hamming_topk": sql([*HAM, "ham AS (SELECT q.id AS query_id, x.id AS vec_id, CAST(sum(bit_count(xor(q.bits, x.bits))) AS BIGINT) AS score FROM halves q JOIN halves x ON q.half = x.half WHERE q.id % 5 = 0 AND x.id % 5 <> 0 GROUP BY q.id, x.id)"], ranked("ham", 10)),
    "gemm_norm_identity": sql(EXACT, "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(CASE WHEN gap > 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS violations, round(max(gap), 6) AS max_gap FROM (SELECT abs(greatest(0, list_inner_product(q, q) + list_inner_product(x, x) - 2 * list_inner_product(q, x)) - score) AS gap FROM exact JOIN pairs USING (query_id, vec_id))"),
    "matmul_coord": sql([*VECS, *PAIRS], "SELECT query_id AS i, vec_id AS j, round(list_inner_product(q, x), 6) AS v FROM pairs"),
    "matmul_approx": sql(btq(16, "dot"), "SELECT query_id AS i, vec_id AS j, round(score / a + b, 6) AS v FROM scan, bias"),
    "naive_table_saturation": sql([*books(16, 16), table_of("qy", "q.id % 5 = 0", "sql2")], "SELECT scale::DOUBLE AS scale, round(avg(CASE WHEN floor(y * scale * scale) <= 0 THEN 1.0 ELSE 0 END), 6) AS share0, round(avg(CASE WHEN floor(y * scale * scale) >= 255 THEN 1.0 ELSE 0 END), 6) AS share255 FROM qy, (SELECT unnest([0.001, 1.0, 1000.0]) AS scale) GROUP BY scale"),
    "lemma_cauchy": "",
    "lemma_triangle": "",
    "lemma_entry_error": sql([*books(16, 16), *quantizer("sql2"), table_of("qy", "q.id % 5 = 0", "sql2")], "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(CASE WHEN gap < -1e-9 OR gap >= 1 / scale + 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS violations, round(max(gap), 6) AS max_gap FROM (SELECT scale, y - (floor(round(scale * (y - lo), 9)) / scale + lo) AS gap FROM qy JOIN tq USING (m) WHERE floor(round(scale * (y - lo), 9)) BETWEEN 0 AND 255)"),
    "coarse_cell_scan": sql([*model(1, 16), table_of("qy", "q.id % 5 = 0", "sql2"), *EXACT, "near AS (SELECT query_id, i FROM qy QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(y, 9), i) <= 4)", "inside AS (SELECT e.query_id, e.vec_id, e.score FROM exact e JOIN codes c ON c.id = e.vec_id JOIN near n ON n.query_id = e.query_id AND n.i = c.i)"], R6.format(ranked("inside", 10))),
    "range_search": sql(btq(16), f"SELECT query_id, vec_id, round({APPROX_L2}, 6) AS dist FROM scan, bias WHERE {APPROX_L2} <= 1.2"),
    "similarity_self_join": sql(VECS, f"SELECT a, b, round(dist, 6) AS dist FROM (SELECT q.id AS a, x.id AS b, sqrt({TRUE_SQ.replace('(q, x)', '(q.v, x.v)')}) AS dist FROM vecs q, vecs x WHERE q.id < x.id) WHERE dist <= 1.1"),
    "codebook_usage": sql(model(16, 16), "SELECT CAST(m AS INTEGER) AS m, CAST(i AS INTEGER) AS i, n, round(n / sum(n) OVER (PARTITION BY m), 6) AS share FROM (SELECT m, i, CAST(count(*) AS BIGINT) AS n FROM codes GROUP BY m, i)"),
    "overlap_at_k": sql([*btq(16), *EXACT, f"e AS ({ranked('exact', 10)})", f"s AS ({ranked('scan', 10)})"], "SELECT query_id, round(CAST(count(s.vec_id) AS DOUBLE) / 10, 6) AS overlap FROM e LEFT JOIN s USING (query_id, vec_id) GROUP BY query_id"),
    "ops_merge_final": sql([*books(16, 16), "after AS (SELECT id, d, CASE WHEN id % 7 = 0 THEN (SELECT o.x FROM elem o WHERE o.id = elem.id AND o.d = 63 - elem.d) ELSE x END AS x FROM elem WHERE id % 11 <> 0)", assigned("codes", "after", f"c{ITERS}")], CODE_ROWS),
    "walk_vectors": "WITH s AS (SELECT event_id, event_type, ts, sum(value - 50) OVER w AS s, row_number() OVER w AS nth FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)), l AS (SELECT event_id, nth, list(s) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 127 PRECEDING AND CURRENT ROW) AS v FROM s) SELECT event_id AS id, CAST(unnest(range(128)) AS INTEGER) AS d, round(unnest(list_transform(v, lambda x: (x - v[1]) / 100)), 6) AS v FROM l WHERE nth >= 128",
    "text_vectors": "WITH w AS (SELECT doc_id AS id, CAST('0x' || substr(md5(word), 1, 8) AS BIGINT) % 512 AS d FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{L}]+')) AS word FROM documents) WHERE word <> ''), n AS (SELECT id, d, count(*) AS n FROM w GROUP BY id, d), t AS (SELECT id, sqrt(sum(n * n)) AS norm FROM n GROUP BY id), g AS (SELECT doc_id AS id, unnest(range(512)) AS d FROM documents) SELECT g.id, CAST(g.d AS INTEGER) AS d, round(coalesce(n.n / t.norm, 0.0), 6) AS v FROM g LEFT JOIN n ON g.id = n.id AND g.d = n.d LEFT JOIN t ON g.id = t.id",
    "part_vectors": "WITH q AS (SELECT l_partkey AS id, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS d, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2), g AS (SELECT DISTINCT id FROM q WHERE d BETWEEN 0 AND 83) SELECT g.id, CAST(r.d AS INTEGER) AS d, round(coalesce(q.q, 0.0), 6) AS v FROM g CROSS JOIN (SELECT unnest(range(84)) AS d) r LEFT JOIN q ON q.id = g.id AND q.d = r.d",
    "events_tumbling": f"WITH w AS (SELECT user_id, time_bucket(INTERVAL 1 day, ts) AS s, time_bucket(INTERVAL 1 day, ts) + INTERVAL 1 day AS e, {WINDOW_FEATURES} FROM events GROUP BY ALL) {EVENT_ROWS}",
    "events_sliding": f"WITH x AS (SELECT *, time_bucket(INTERVAL 12 hour, ts) - to_hours(12 * k) AS s FROM events, (SELECT unnest([0, 1]) AS k)), w AS (SELECT user_id, s, s + INTERVAL 1 day AS e, {WINDOW_FEATURES} FROM x GROUP BY user_id, s) {EVENT_ROWS}",
    "events_session": f"WITH f AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 hour THEN 1 ELSE 0 END AS new FROM events), x AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS sid FROM f), w AS (SELECT user_id, min(ts) AS s, max(ts) + INTERVAL 6 hour AS e, {WINDOW_FEATURES} FROM x GROUP BY user_id, sid) {EVENT_ROWS}",
    "split_counts": "SELECT CASE WHEN vec_id % 5 = 0 THEN 'query' ELSE 'database' END AS part, CAST(count(*) AS BIGINT) AS n FROM embeddings GROUP BY 1",
    "subspace_balance_corr": sql(ELEM, "SELECT CAST(a.d AS INTEGER) AS d, round(corr(a.x, b.x), 6) AS value FROM elem a JOIN elem b ON a.id = b.id AND b.d = a.d + 1 GROUP BY a.d"),
    "asof_model_version": "SELECT event_id, CAST(CASE WHEN ts >= TIMESTAMP '2024-01-21' THEN 3 WHEN ts >= TIMESTAMP '2024-01-11' THEN 2 WHEN ts >= TIMESTAMP '2024-01-02' THEN 1 END AS INTEGER) AS version FROM events",
    "cube_usage": sql(model(16, 16), "SELECT CAST(m AS INTEGER) AS m, CAST(label AS INTEGER) AS label, CAST(count(*) AS BIGINT) AS n, CAST(count(DISTINCT i) AS BIGINT) AS used FROM codes JOIN embeddings ON codes.id = vec_id GROUP BY CUBE (m, label)"),
    "rollup_usage": sql(model(16, 16), "SELECT CAST(m AS INTEGER) AS m, CAST(label AS INTEGER) AS label, CAST(count(*) AS BIGINT) AS n, CAST(count(DISTINCT i) AS BIGINT) AS used FROM codes JOIN embeddings ON codes.id = vec_id GROUP BY ROLLUP (m, label)"),
}

PART = "WITH q AS (SELECT l_partkey AS id, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS d, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2), g AS (SELECT DISTINCT id FROM q WHERE d BETWEEN 0 AND 83), vecs AS MATERIALIZED (SELECT g.id, list(coalesce(q.q, 0.0) ORDER BY r.d) AS v FROM g CROSS JOIN (SELECT unnest(range(84)) AS d) r LEFT JOIN q ON q.id = g.id AND q.d = r.d GROUP BY g.id), "
ORACLES["exact_mips"] = PART + "exact AS MATERIALIZED (SELECT q.id AS query_id, x.id AS vec_id, round(list_inner_product(q.v, x.v), 6) AS score FROM vecs q, vecs x WHERE q.id % 5 = 0 AND x.id % 5 <> 0) " + ranked("exact", 10, "DESC")

_BOUNDS = [*RECON, *VECS, "back AS MATERIALIZED (SELECT id, list(y ORDER BY d) AS y FROM recon GROUP BY id)"]
_GAPS = "SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(CASE WHEN gap > bound + 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS violations, round(max(gap), 6) AS max_gap FROM ({})"
_ERR = "sqrt(list_sum(list_transform(list_zip(x.v, b.y), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))"
_FROM = "FROM vecs q, vecs x JOIN back b ON b.id = x.id WHERE q.id % 5 = 0 AND x.id % 5 <> 0"
ORACLES["lemma_cauchy"] = sql(_BOUNDS, _GAPS.format(f"SELECT abs(list_inner_product(q.v, x.v) - list_inner_product(q.v, b.y)) AS gap, sqrt(list_inner_product(q.v, q.v)) * {_ERR} AS bound {_FROM}"))
ORACLES["lemma_triangle"] = sql(_BOUNDS, _GAPS.format(f"SELECT abs(sqrt(list_sum(list_transform(list_zip(q.v, x.v), lambda p: (p[1] - p[2]) * (p[1] - p[2])))) - sqrt(list_sum(list_transform(list_zip(q.v, b.y), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))) AS gap, {_ERR} AS bound {_FROM}"))

# ------------------------------------------------- queries of the same answer by another way, and what is fitted

ORACLES["fast_codes_near"] = "SELECT CAST(16 * count(*) AS BIGINT) AS n, CAST(16 * count(*) AS BIGINT) AS near FROM embeddings"
ORACLES["gemm_topk"] = sql(EXACT, R6.format(ranked("exact", 10)))
ORACLES["product_cell_scan"] = sql(
    [
        *model(2, 8),
        table_of("qy", "q.id % 5 = 0", "sql2"),
        *EXACT,
        "cells AS (SELECT a.query_id, a.i AS i0, b.i AS i1, round(a.y + b.y, 9) AS y FROM qy a JOIN qy b ON a.query_id = b.query_id WHERE a.m = 0 AND b.m = 1)",
        "near AS (SELECT query_id, i0, i1 FROM cells QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY y, 8 * i0 + i1) <= 32)",
        "inside AS (SELECT e.query_id, e.vec_id, e.score FROM exact e JOIN codes c ON c.id = e.vec_id AND c.m = 0 JOIN codes d ON d.id = e.vec_id AND d.m = 1 JOIN near n ON n.query_id = e.query_id AND n.i0 = c.i AND n.i1 = d.i)",
    ],
    R6.format(ranked("inside", 10)),
)
ORACLES["constant_loss"] = sql(EXACT, "SELECT CAST(count(*) AS BIGINT) AS n, round(var_pop(sqrt(score)), 6) AS value FROM exact")
ORACLES["codebook_entropy"] = sql(model(16, 16), "SELECT CAST(m AS INTEGER) AS m, round(-sum(p * log2(p)), 6) AS bits FROM (SELECT m, count(*) / sum(count(*)) OVER (PARTITION BY m) AS p FROM codes GROUP BY m, i) GROUP BY m")
ORACLES["streaming_topk"] = sql(btq(16), "SELECT query_id, rnk, vec_id, CAST(score AS BIGINT) AS score, round(greatest(0.0, score / a + b), 6) AS dist FROM (" + ranked("scan", 10) + "), bias")
_WIDE = "[" + ", ".join(["coalesce(sum(x) FILTER (d = {}), 0.0)".format(d) for d in range(16)]) + "]"
ORACLES["densify_signhash"] = (
    "WITH q AS (SELECT l_partkey AS id, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS month, sum(l_quantity) AS x FROM lineitem GROUP BY 1, 2), "
    "h AS (SELECT id, CAST('0x' || substr(md5(CAST(month AS VARCHAR)), 1, 8) AS BIGINT) % 16 AS d, x * (1 - 2 * (CAST('0x' || substr(md5(CAST(month AS VARCHAR)), 9, 1) AS INTEGER) & 1)) AS x FROM q WHERE month BETWEEN 0 AND 83), "
    f"w AS (SELECT id, {_WIDE} AS vec FROM h GROUP BY id) SELECT id, CAST(unnest(range(16)) AS INTEGER) AS d, round(unnest(vec), 6) AS v FROM w"
)


def _variant(pool: str, weight: str, half: bool) -> str:
    back = f"(greatest(0, least(255, floor(round(scale * (y - lo), 9)))) + {0.5 if half else 0}) / scale + lo"
    loss = f"avg(power({back} - y, 2))" if weight == "uniform" else f"sum(power({back} - y, 2) * n) / sum(n)"
    joined = f"fy JOIN {pool}cut USING (m)" + ("" if weight == "uniform" else " JOIN (SELECT m, i, count(*) AS n FROM codes WHERE id % 5 <> 0 GROUP BY m, i) u USING (m, i)")
    return f"SELECT '{pool}' AS pool, '{weight}' AS weight, {str(half).lower()} AS midpoint, alpha::DOUBLE AS alpha, round(max(scale), 6) AS scale, round({loss}, 8) AS loss FROM {joined} GROUP BY alpha"


ORACLES["alpha_variants"] = sql(
    [
        *model(16, 16),
        *quantizer("sql2"),
        "shiftedcut AS (SELECT * FROM cut)",
        f"ends AS (SELECT unnest(range(8)) AS g, unnest(quantile_cont(y, {ALPHAS})) AS l, unnest(quantile_cont(y, list_transform({ALPHAS}, lambda a: 1 - a))) AS h FROM fy)",
        "rawcut AS (SELECT low.g, alpha, m, lo, CASE WHEN h > l THEN 255 / (h - l) ELSE 1.0 END AS scale FROM low JOIN ends USING (g))",
    ],
    " UNION ALL ".join(_variant(pool, weight, half) for pool in ("shifted", "raw") for weight in ("uniform", "usage") for half in (False, True)),
)

ORACLES["topk_merge"] = sql(btq(16), "SELECT query_id, rnk, vec_id FROM (" + ranked("scan", 10) + ")")
ORACLES["packed_round_trip"] = "WITH r AS (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS id, embedding FROM embeddings) SELECT id, CAST(unnest(range(64)) AS INTEGER) AS d, round(CAST(unnest(embedding) AS DOUBLE), 6) AS v FROM r"
_SPREADS = [
    *_BOUNDS,
    "rn AS MATERIALIZED (SELECT id, d // 4 AS m, sum((x - y) * (x - y)) AS r FROM recon JOIN elem USING (id, d) GROUP BY id, d // 4)",
    "rl AS MATERIALIZED (SELECT id, list(r ORDER BY m) AS r FROM rn WHERE id % 5 <> 0 GROUP BY id)",
    "ql AS MATERIALIZED (SELECT id, list(s ORDER BY m) AS s FROM (SELECT id, d // 4 AS m, sum(x * x) AS s FROM elem WHERE id % 5 = 0 GROUP BY id, d // 4) GROUP BY id)",
    "gaps AS MATERIALIZED (SELECT abs(list_inner_product(q.v, x.v) - list_inner_product(q.v, b.y)) AS dot, abs(list_sum(list_transform(list_zip(q.v, x.v), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) - list_sum(list_transform(list_zip(q.v, b.y), lambda p: (p[1] - p[2]) * (p[1] - p[2])))) AS sq, list_inner_product(ql.s, rl.r) AS dot_spread, list_inner_product(rl.r, rl.r) AS sq_spread FROM vecs q JOIN ql ON ql.id = q.id, vecs x JOIN back b ON b.id = x.id JOIN rl ON rl.id = x.id WHERE q.id % 5 = 0 AND x.id % 5 <> 0)",
]
_TAIL = "SELECT '{0}' AS kind, eps::DOUBLE AS eps, CAST(count(*) AS BIGINT) AS n, round(avg(CASE WHEN {1} > eps THEN 1.0 ELSE 0.0 END), 6) AS rate, round(avg(CASE WHEN {2} > 0 THEN least(1.0, 2 * exp(-(eps * eps) / (2 * {2}))) ELSE 0.0 END), 6) AS bound FROM gaps, (SELECT unnest([0.1, 0.3, 1.0, 2.0]) AS eps) GROUP BY eps"
ORACLES["tail_bounds"] = sql(_SPREADS, _TAIL.format("dot", "dot", "dot_spread") + " UNION ALL " + _TAIL.format("sql2", "sq", "sq_spread"))
