"""DuckDB SQL for the queries that SQL can express: the exact answers, by other ways than the joins take."""

from __future__ import annotations

from .functions.families import md5_coordinate
from .functions.features import EVENT_TYPES
from .queries import CDF_BINS

H15 = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"
TOKENS = "regexp_extract_all(lower({}), '[a-z0-9]+')"
DOCS = f"SELECT doc_id AS id, unnest({TOKENS.format('text')}) AS t FROM documents"


def sets(rows: str, similar: str, r: float, pair: str = "a.id < b.id") -> str:
    """Near pairs of sets by shared items; rows gives distinct (id, t)."""
    return f"""
WITH t AS ({rows}), n AS (SELECT id, count(*) AS c FROM t GROUP BY id),
p AS (SELECT a.id AS id_l, b.id AS id_r, count(*) AS k FROM t a JOIN t b ON a.t = b.t AND {pair} GROUP BY 1, 2),
j AS (SELECT id_l, id_r, k / CAST(x.c + y.c - k AS DOUBLE) AS s FROM p JOIN n x ON x.id = id_l JOIN n y ON y.id = id_r)
SELECT id_l, id_r, {similar} FROM j WHERE s >= {r}"""


DIST = "round(1 - s, 6) + 0.0 AS dist"
WORDS = f"SELECT DISTINCT id, t FROM ({DOCS})"
SHINGLES = f"SELECT DISTINCT id, t FROM (SELECT doc_id AS id, unnest(list_transform(range(1, greatest(len(w) - 1, 1)), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS t FROM (SELECT doc_id, {TOKENS.format('text')} AS w FROM documents) WHERE len(w) >= 3)"
PAGES = f"SELECT DISTINCT page_id AS id, unnest({TOKENS.format('html')}) AS t FROM pages"
CONV = f"SELECT DISTINCT conv_id * 1000 + turn AS id, unnest({TOKENS.format('text')}) AS t FROM conversations"
BRANDS = "SELECT DISTINCT o_custkey AS id, p_brand AS t FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey"
BRAND_LINKS = f"""
WITH s AS (SELECT id, list(t ORDER BY t) AS l FROM ({BRANDS}) GROUP BY id), c AS (SELECT id, min(id) OVER (PARTITION BY l) AS class_id FROM s),
p AS (SELECT id_l, id_r FROM ({sets(BRANDS, DIST, 0.7)})), e AS (SELECT id_l AS id, count(*) AS n FROM p GROUP BY 1 UNION ALL SELECT id_r, count(*) FROM p GROUP BY 1)
SELECT c.id, class_id, CAST(coalesce(sum(n), 0) AS BIGINT) AS links FROM c LEFT JOIN e ON e.id = c.id GROUP BY 1, 2"""
W1, W1S = sets(WORDS, DIST, 0.5), sets(SHINGLES, DIST, 0.5)
PAIRS = f"SELECT id_l, id_r, dist FROM ({W1})"
RS = f"""
WITH a AS (SELECT DISTINCT item_id AS id, unnest({TOKENS.format('text')}) AS t FROM benchmark),
l AS (SELECT doc_id * 100000 + unnest(range(0, len(s))) AS id, unnest(s) AS line FROM (SELECT doc_id, string_split(text, chr(10)) AS s FROM documents)),
b AS (SELECT DISTINCT id, unnest({TOKENS.format('line')}) AS t FROM l),
na AS (SELECT id, count(*) AS c FROM a GROUP BY id), nb AS (SELECT id, count(*) AS c FROM b GROUP BY id),
p AS (SELECT a.id AS id_l, b.id AS id_r, count(*) AS k FROM a JOIN b USING (t) GROUP BY 1, 2)
SELECT id_l, id_r, round(1 - k / CAST(na.c + nb.c - k AS DOUBLE), 6) AS dist FROM p JOIN na ON na.id = id_l JOIN nb ON nb.id = id_r WHERE k / CAST(na.c + nb.c - k AS DOUBLE) >= 0.3"""

SLOTS = f"SELECT doc_id AS id, CAST('0x' || substr(md5(unnest({TOKENS.format('text')})), 1, 8) AS BIGINT) % 64 AS s FROM documents"
L1_ALL = f"""
WITH d AS (SELECT doc_id AS id FROM documents), g AS (SELECT id, s, count(*) AS c FROM ({SLOTS}) GROUP BY 1, 2),
v AS (SELECT d.id, list(coalesce(g.c, 0) ORDER BY k.s) AS v FROM d CROSS JOIN range(64) k(s) LEFT JOIN g ON g.id = d.id AND g.s = k.s GROUP BY d.id),
p AS (SELECT a.id AS id_l, b.id AS id_r, list_sum(list_transform(list_zip(a.v, b.v), lambda z: abs(z[1] - z[2]))) AS d FROM v a JOIN v b ON a.id < b.id)
"""
L1 = f"{L1_ALL} SELECT id_l, id_r, round(CAST(d AS DOUBLE), 6) AS dist FROM p WHERE d <= 40"
SIGNED = f"SELECT id, h % 256 AS s, sum(CASE WHEN (h // 256) % 2 = 1 THEN 1 ELSE -1 END) AS v FROM (SELECT id, {H15.format('t')} AS h FROM ({WORDS})) GROUP BY 1, 2"
COS_DOCS = f"""
WITH g AS ({SIGNED}), n AS (SELECT id, sqrt(CAST(sum(v * v) AS DOUBLE)) AS n FROM g GROUP BY id),
p AS (SELECT a.id AS id_l, b.id AS id_r, CAST(sum(a.v * b.v) AS DOUBLE) AS d FROM g a JOIN g b ON a.s = b.s AND a.id < b.id GROUP BY 1, 2)
SELECT id_l, id_r, round(1 - d / (x.n * y.n), 6) + 0.0 AS dist FROM p JOIN n x ON x.id = id_l JOIN n y ON y.id = id_r WHERE d / (x.n * y.n) >= 0.7"""
EMB = "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings"
EMB_PAIRS = f"WITH e AS ({EMB}), p AS (SELECT a.id AS id_l, b.id AS id_r, sqrt(list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS d, list_cosine_similarity(a.v, b.v) AS c FROM e a JOIN e b ON a.id < b.id)"
L2 = f"{EMB_PAIRS} SELECT id_l, id_r, round(d, 6) AS dist FROM p WHERE d <= 1.1"
COS_EMB = f"{EMB_PAIRS} SELECT id_l, id_r, round(1 - c, 6) + 0.0 AS dist FROM p WHERE c >= 0.4"
CLOSE_EMB = f"SELECT id_l AS id, id_r AS other, c AS cos FROM ({EMB_PAIRS} SELECT * FROM p WHERE c >= 0.2) UNION ALL SELECT id_r, id_l, c FROM ({EMB_PAIRS} SELECT * FROM p WHERE c >= 0.2)"
FINGER = f"""SELECT id, CAST(list_sum(list_transform(range(0, 64), lambda b: CASE WHEN bits[b + 1] > 0 THEN CAST(1 AS HUGEINT) << b ELSE CAST(0 AS HUGEINT) END)) AS HUGEINT) AS f FROM (
  SELECT id, list(v ORDER BY b) AS bits FROM (
    SELECT id, b, sum(CASE WHEN (CASE WHEN b < 32 THEN lo >> b ELSE hi >> (b - 32) END) & 1 = 1 THEN 1 ELSE -1 END) AS v FROM (
      SELECT id, CAST('0x' || substr(md5(t), 1, 8) AS BIGINT) AS hi, CAST('0x' || substr(md5(t), 9, 8) AS BIGINT) AS lo FROM ({WORDS})), range(64) r(b) GROUP BY id, b) GROUP BY id)"""
FINGERS = f"SELECT d.doc_id AS id, coalesce(f.f, 0) AS f FROM documents d LEFT JOIN ({FINGER}) f ON f.id = d.doc_id"
HAM = f"WITH f AS ({FINGERS}) SELECT a.id AS id_l, b.id AS id_r, CAST(bit_count(xor(a.f, b.f)) AS DOUBLE) AS dist FROM f a JOIN f b ON a.id < b.id WHERE bit_count(xor(a.f, b.f)) <= 10"
SIGN = "SELECT vec_id AS id, list_sum(list_transform(range(0, 64), lambda i: CASE WHEN embedding[i + 1] > 0 THEN CAST(1 AS HUGEINT) << i ELSE CAST(0 AS HUGEINT) END)) AS f FROM embeddings"
HAM_EMB = f"WITH f AS (SELECT id, CAST(f AS HUGEINT) AS f FROM ({SIGN})) SELECT a.id AS id_l, b.id AS id_r, CAST(bit_count(xor(a.f, b.f)) AS DOUBLE) AS dist FROM f a JOIN f b ON a.id < b.id WHERE bit_count(xor(a.f, b.f)) <= 16"
USERS = f"""
WITH u AS (SELECT DISTINCT user_id FROM events), k AS (SELECT * FROM (VALUES {', '.join(f"('{k}')" for k in EVENT_TYPES)}) x(k), range(4) b(b)),
g AS (SELECT user_id, event_type, hour(ts) // 6 AS b, count(*) AS c FROM events GROUP BY ALL),
v AS (SELECT u.user_id AS id, list(coalesce(g.c, 0) ORDER BY k.k, k.b) AS v FROM u CROSS JOIN k LEFT JOIN g ON g.user_id = u.user_id AND g.event_type = k.k AND g.b = k.b GROUP BY 1)
SELECT a.id AS id_l, b.id AS id_r, CAST(list_sum(list_transform(list_zip(a.v, b.v), lambda z: abs(z[1] - z[2]))) AS DOUBLE) AS dist FROM v a JOIN v b ON a.id < b.id
WHERE list_sum(list_transform(list_zip(a.v, b.v), lambda z: abs(z[1] - z[2]))) <= 20"""


def md5_keys() -> str:
    bits = lambda rep: " || ".join(f"CAST((f >> {md5_coordinate(7, rep, j)}) & 1 AS VARCHAR)" for j in range(8))
    return " UNION ALL ".join(f"SELECT id, f, {rep} AS rep, {bits(rep)} AS key FROM f" for rep in range(4))


MD5 = f"WITH f AS ({FINGERS}), k AS ({md5_keys()}), p AS (SELECT a.rep, a.id AS id_l, b.id AS id_r, bit_count(xor(a.f, b.f)) AS d FROM k a JOIN k b ON a.rep = b.rep AND a.key = b.key AND a.id < b.id)"
MINHASH = "WITH t AS (SELECT id, " + H15.format("t") + f" AS t FROM ({WORDS})), h AS (SELECT rep, id, " + ", ".join(f"min({H15.format(f'''concat('7:', rep, ':{j}:', t)''')}) AS h{j}" for j in range(2)) + " FROM t, range(4) r(rep) GROUP BY 1, 2), s AS (SELECT rep, h0, h1, count(*) AS n FROM h GROUP BY ALL) SELECT CAST(rep AS INTEGER) AS rep, count(*) AS buckets, max(n) AS largest, CAST(sum(n * (n - 1) // 2) AS BIGINT) AS pairs FROM s GROUP BY rep"
VALUE_BINS = lambda bins: ", ".join(f"({b!r}::DOUBLE)" for b in bins)
CDF_W1 = f"WITH j AS (SELECT 1 - dist AS s0, * FROM ({sets(WORDS, 's', 0.0)}) x(id_l, id_r, dist)), v AS (SELECT dist AS s FROM j) SELECT t AS threshold, CAST((SELECT count(*) FROM v WHERE s >= t) AS BIGINT) AS pairs FROM (VALUES {VALUE_BINS(CDF_BINS['W1'])}) b(t)"
CDF_L1 = f"SELECT t AS threshold, CAST(count(d) AS BIGINT) AS pairs FROM (VALUES {VALUE_BINS(CDF_BINS['W3'])}) b(t) LEFT JOIN ({L1_ALL} SELECT d FROM p WHERE d <= 160) q ON d <= t GROUP BY t"
CDF_L2 = f"SELECT t AS threshold, CAST(count(d) AS BIGINT) AS pairs FROM (VALUES {VALUE_BINS(CDF_BINS['W4'])}) b(t) LEFT JOIN ({EMB_PAIRS} SELECT d FROM p) q ON d <= t GROUP BY t"
COS_ALL = COS_DOCS.split("SELECT id_l, id_r, round")[0]
CDF_COS = f"SELECT t AS threshold, CAST(count(c) AS BIGINT) AS pairs FROM (VALUES {VALUE_BINS(CDF_BINS['W2'])}) b(t) LEFT JOIN ({COS_ALL} SELECT d / (x.n * y.n) AS c FROM p JOIN n x ON x.id = id_l JOIN n y ON y.id = id_r) q ON c >= t GROUP BY t"
EVEN_ODD = f"SELECT CASE WHEN id_l % 2 = 0 THEN id_l ELSE id_r END AS id_l, CASE WHEN id_l % 2 = 0 THEN id_r ELSE id_l END AS id_r, dist FROM ({W1}) WHERE (id_l + id_r) % 2 = 1"
SIZES = f"WITH j AS ({sets(WORDS, 's', 0.0)}), n AS (SELECT count(*) AS n FROM documents) SELECT count(*) FILTER (s >= 0.5) AS near, count(*) FILTER (s >= 0.1 AND s < 0.5) AS grey, CAST(any_value(n * (n - 1) // 2) - count(*) FILTER (s >= 0.1) AS BIGINT) AS far FROM j, n"
GROWTH = f"SELECT round(regr_slope(ln(pairs), ln(threshold)), 6) AS exponent, round(regr_r2(ln(pairs), ln(threshold)), 6) AS fit FROM ({CDF_L1}) WHERE threshold BETWEEN 20 AND 120 AND pairs > 0"
T1T2 = f"WITH s AS ({SIZES}), d AS (SELECT 2.0 * count(*) AS n FROM documents), g AS (SELECT CAST(pow(2, i) AS DOUBLE) AS share FROM range(1, 9) r(i)), q AS (SELECT share, pow(share, ln(0.5) / ln(0.1)) * (n + near / (n / share)) AS t1, (near + grey) / (n / share) AS t2 FROM s, d, g) SELECT CAST(share AS BIGINT) AS n_over_memory, round(t1, 3) AS t1, round(t2, 3) AS t2, round(t1 / t2, 3) AS ratio FROM q"
RHO = """WITH r(work, r, cr) AS (VALUES ('W1', 0.5, 0.1), ('W2', 0.7, 0.2), ('W3', 40.0, 80.0), ('W6', 10.0, 20.0)),
q AS (SELECT work, unnest([1, 2]) AS k, unnest([CAST(r AS DOUBLE), CAST(cr AS DOUBLE)]) AS x FROM r),
p AS (SELECT work, k, CASE work WHEN 'W1' THEN x WHEN 'W2' THEN 1 - acos(least(x, 1.0)) / pi() WHEN 'W3' THEN 2 * atan(160 / x) / pi() - ln(1 + (160 / x) * (160 / x)) / (pi() * (160 / x)) ELSE 1 - x / 64 END AS p FROM (SELECT work, k, CASE WHEN work = 'W2' THEN x ELSE x END AS x FROM q) WHERE work <> 'W2' OR x <= 1),
w AS (SELECT work, max(p) FILTER (k = 1) AS p1, max(p) FILTER (k = 2) AS p2 FROM p GROUP BY work)
SELECT work, round(p1, 6) AS p1, round(p2, 6) AS p2, round(ln(p1) / ln(p2), 6) AS rho, CAST(greatest(1, ceil(ln(125 / (2.0 * n)) / ln(p2) - 1e-9)) AS BIGINT) AS k FROM w, (SELECT count(text) AS n FROM documents)"""
HEAVY = f"WITH t AS ({BRANDS}), n AS (SELECT id, count(*) AS c FROM t GROUP BY id), p AS (SELECT a.id AS id_l, b.id AS id_r, count(*) AS k FROM t a JOIN t b ON a.t = b.t GROUP BY 1, 2), s AS (SELECT id_l AS id, count(*) AS close FROM p JOIN n x ON x.id = id_l JOIN n y ON y.id = id_r WHERE k / CAST(x.c + y.c - k AS DOUBLE) >= 0.5 GROUP BY 1), o AS (SELECT count(*) AS o FROM n) SELECT id, close, o AS \"of\" FROM s, o WHERE 2 * close >= o"
CLUSTERS = f"WITH RECURSIVE e AS (SELECT id_l AS a, id_r AS b FROM ({PAIRS}) UNION ALL SELECT id_r, id_l FROM ({PAIRS})), r(id, c) AS (SELECT DISTINCT a, a FROM e UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.c) SELECT id, min(c) AS cluster FROM r GROUP BY id"
BOTH = f"SELECT id_l AS id, id_r AS other, dist FROM ({PAIRS}) UNION ALL SELECT id_r, id_l, dist FROM ({PAIRS})"
MARK = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"


def core() -> dict[str, str]:
    same = {
        W1: "exact_jaccard_docs aware_jaccard_docs aware_capped_docs lookback_dedup_docs oblivious_jaccard_docs single_level_jaccard_docs prefix_filter_docs positional_filter_docs length_filter_docs pair_sink",
        W1S: "exact_shingles_docs aware_shingles_docs inverted_index_docs",
        COS_DOCS: "exact_cosine_docs aware_cosine_docs oblivious_cosine_docs",
        L1: "exact_l1_docs aware_l1_docs oblivious_l1_docs block_nested_l1_docs recursive_nested_l1_docs",
        EVEN_ODD: "aware_even_odd_docs", HAM: "exact_hamming_docs aware_hamming_docs aware_custom_family oblivious_hamming_docs",
        L2: "exact_l2_emb aware_l2_emb", COS_EMB: "exact_cosine_emb aware_cosine_emb", HAM_EMB: "exact_hamming_emb aware_hamming_emb stream_static_neardup",
        USERS: "aware_l1_users", RS: "aware_rs_benchmark_lines oblivious_rs_benchmark_lines", sets(BRANDS, DIST, 0.7): "exact_brand_sets oblivious_brand_sets",
        sets(PAGES, DIST, 0.5): "aware_pages", sets(CONV, DIST, 0.2): "conv_near_dups",
    }
    return {name: sql for sql, names in same.items() for name in names.split()}


def measures() -> dict[str, str]:
    return {
        "join_sizes_docs": SIZES, "cdf_jaccard_docs": CDF_W1, "cdf_l1_docs": CDF_L1, "cdf_cosine_docs": CDF_COS, "cdf_l2_emb": CDF_L2, "growth_exponent_docs": GROWTH, "t1_t2_table": T1T2, "rho_table": RHO, "minhash_buckets_md5": MINHASH,
        "bitsample_counters_md5": f"{MD5} SELECT CAST(rep AS INTEGER) AS rep, count(*) FILTER (d <= 10) AS near, count(*) FILTER (d > 10 AND d <= 20) AS grey, count(*) FILTER (d > 20) AS far FROM p GROUP BY rep",
        "far_counters_md5": f"{MD5} SELECT id, count(*) AS far FROM (SELECT id_l AS id FROM p WHERE d > 20 UNION ALL SELECT id_r FROM p WHERE d > 20) GROUP BY id",
        "replication_factor_md5": f"{MD5} SELECT count(*) AS emissions, count(DISTINCT (id_l, id_r)) AS pairs, round(count(*) / CAST(count(DISTINCT (id_l, id_r)) AS DOUBLE), 6) AS replication FROM p WHERE d <= 10",
        "bucket_join_md5": f"{MD5} SELECT id_l, id_r, CAST(d AS INTEGER) AS d, CAST(min(rep) AS BIGINT) AS first_rep FROM p WHERE d <= 10 GROUP BY 1, 2, 3",
        "chunk_numbers_md5": f"{MD5}, c AS (SELECT key, id, (row_number() OVER (PARTITION BY key ORDER BY id) - 1) // 64 AS chunk FROM k WHERE rep = 0) SELECT key, chunk, count(*) AS points, min(id) AS first FROM c GROUP BY 1, 2",
        "skewed_buckets_md5": f"{MD5} SELECT CAST(rep AS INTEGER) AS rep, key, count(*) AS points FROM k GROUP BY 1, 2 ORDER BY points DESC, rep, key LIMIT 20",
        "heavy_points_exact": HEAVY, "dup_clusters": CLUSTERS, "cte_clusters": f"SELECT id, cluster AS lowest FROM ({CLUSTERS})",
        "aware_brand_sets": BRAND_LINKS, "aware_until_recall_docs": PAIRS, "aware_guaranteed_hamming_docs": HAM, "oblivious_guaranteed_hamming_docs": HAM, "oblivious_race_docs": PAIRS,
        "recall_report": f"SELECT count(*) AS found, count(*) AS truth, count(*) AS \"both\", 1.0::DOUBLE AS recall, 1.0::DOUBLE AS precision FROM ({PAIRS})",
        "monotone_check": "SELECT family, CAST(0 AS BIGINT) AS grows, (SELECT count(DISTINCT length(text)) - 1 FROM documents WHERE length(text) BETWEEN 1 AND 399) AS steps FROM (VALUES ('hamming'), ('jaccard'), ('cosine'), ('l2')) f(family)",
        "cost_table": """WITH p(data, metric, r, cr, rho, near, close) AS (VALUES ('text', 'jaccard', 0.5::DOUBLE, 0.1::DOUBLE, 0.30::DOUBLE, 1800.0::DOUBLE, 16000.0::DOUBLE), ('text', 'cosine', 0.7, 0.2, 0.51, 1600.0, 16000.0), ('digits', 'l1', 3000, 6000, 0.50, 1.8, 42.0)), q AS (SELECT p.*, n FROM p, (SELECT CAST(count(text) AS DOUBLE) AS n FROM documents))
SELECT data, metric, r, cr, rho, CAST(n AS BIGINT) AS points, CAST(round(2 * n + n * n / (n / 1000)) AS BIGINT) AS io_nested, CAST(round(8 * pow(n, 1 + rho)) AS BIGINT) AS io_single_level, CAST(round(pow(n / (n / 1000), rho) * (n + near * n / (n / 1000))) AS BIGINT) AS t1, CAST(round(close * n / (n / 1000)) AS BIGINT) AS t2 FROM q""",
    }


def surface() -> dict[str, str]:
    top = f"SELECT id, other, row_number() OVER (PARTITION BY id ORDER BY cos DESC, other) AS place FROM ({CLOSE_EMB})"
    return {
        "scan_pruned_lineitem": "SELECT l_quantity, count(*) AS n, max(l_orderkey) AS last_order FROM lineitem WHERE l_quantity >= 45 AND l_discount <= 0.02 GROUP BY 1",
        "roundtrip_csv_region": "SELECT r_regionkey, r_name FROM region",
        "load_points_emb": "SELECT vec_id AS id, CAST(64 AS INTEGER) AS dim, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm2 FROM embeddings",
        "hash_index": HAM,
        "cluster_source": f"WITH f AS (SELECT id, CAST(f AS HUGEINT) AS f, id * 11 % 64 AS b FROM ({SIGN})), m AS (SELECT id, xor(f, ((CAST(7 AS HUGEINT) << CAST(b AS INTEGER)) & 18446744073709551615::HUGEINT) | (CAST(7 AS HUGEINT) >> CAST(64 - b AS INTEGER))) AS w FROM f) SELECT label AS cluster, count(*) AS points, count(DISTINCT w) AS words FROM m JOIN embeddings ON vec_id = id GROUP BY 1",
        "project_features": f"SELECT doc_id, len({TOKENS.format('text')}) AS n_tokens, length(text) AS chars, lower(substr(text, 1, 3)) AS head, lang FROM documents",
        "filter_ring_l2": f"{EMB_PAIRS} SELECT id_l, id_r, round(d, 6) AS dist FROM p WHERE d > 1.1 AND d <= 1.2",
        "filter_docs_predicates": "SELECT doc_id, lang, source FROM documents WHERE text IS NOT NULL AND lang IN ('en', 'de') AND source LIKE 'src1%' AND regexp_matches(text, '^[A-Z]') AND n_chars BETWEEN 100 AND 5000",
        "order_line_smj": "SELECT o_orderpriority, count(*) AS items, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1",
        "nation_region_bcast": "SELECT r_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
        "price_band_range_join": "SELECT a.p_type, count(*) AS pairs FROM part a JOIN part b ON a.p_type = b.p_type AND a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 1 GROUP BY 1",
        "events_interval_join": "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR GROUP BY 1",
        "asof_last_event": "SELECT p.event_id, p.user_id, (SELECT v.event_id FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts, v.event_id) < (p.ts, p.event_id) ORDER BY v.ts DESC, v.event_id DESC LIMIT 1) AS view_id FROM events p WHERE p.event_type = 'purchase'",
        "both_sides_semi": f"SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT id_l FROM ({PAIRS}))",
        "docs_without_near_dup": f"SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT id FROM ({BOTH}))",
        "lateral_topk": f"SELECT id AS vec_id, other FROM ({top}) WHERE place <= 3",
        "topk_neighbours": f"SELECT id, other, CAST(place AS INTEGER) AS place FROM ({top}) WHERE place <= 3",
        "rollup_levels": "SELECT lang, source, count(*) AS docs, grouping(lang, source) AS level FROM documents GROUP BY ROLLUP (lang, source)",
        "neardup_by_source_lang_cube": f"SELECT lang, source, count(*) AS pairs FROM ({PAIRS}) JOIN documents ON id_l = doc_id GROUP BY CUBE (lang, source)",
        "gsets_lang_quality": "SELECT lang, quality, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY GROUPING SETS ((lang, quality), (lang), ())",
        "pivot_event_hist": "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "clusters_listed": f"SELECT cluster, string_agg(CAST(id AS VARCHAR), ',' ORDER BY id) AS members, count(*) AS n FROM ({CLUSTERS}) GROUP BY 1",
        "nearest_doc": f"WITH b AS ({BOTH}) SELECT id, (SELECT other FROM b x WHERE x.id = b.id ORDER BY dist, other LIMIT 1) AS nearest, (SELECT other FROM b x WHERE x.id = b.id ORDER BY dist DESC, other DESC LIMIT 1) AS farthest FROM b GROUP BY id",
        "sample_larger_md5": f"SELECT source, doc_id, CAST(place AS INTEGER) AS place FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY {MARK.format('''concat('7:', doc_id)''')}, doc_id) AS place FROM documents) WHERE place <= 5",
        "rank_neighbours": f"SELECT id_l AS id, id_r AS other, CAST(rank() OVER w AS INTEGER) AS rank, CAST(dense_rank() OVER w AS INTEGER) AS dense_rank FROM (SELECT *, round(1 - dist, 2) AS s FROM ({PAIRS})) WINDOW w AS (PARTITION BY id_l ORDER BY s DESC)",
        "events_range_frame": "SELECT event_id, recent FROM (SELECT event_id, event_type, count(*) OVER (PARTITION BY user_id ORDER BY CAST(epoch(date_trunc('second', ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events) WHERE event_type = 'purchase'",
        "window_frames_cdf": "SELECT doc_id, round(percent_rank() OVER w, 6) AS percent_rank, round(cume_dist() OVER w, 6) AS cume_dist, first_value(doc_id) OVER a AS first_doc, last_value(doc_id) OVER a AS last_doc, nth_value(doc_id, 2) OVER a AS second_doc FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id), a AS (PARTITION BY lang ORDER BY n_chars, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
        "closest_pairs_top": f"{EMB_PAIRS} SELECT id_l, id_r, round(d, 6) AS dist FROM p WHERE d <= 1.1 ORDER BY dist, id_l, id_r LIMIT 10",
        "pairs_union": f"SELECT DISTINCT id_l, id_r FROM ({PAIRS}) WHERE id_l % 2 = 0 OR id_r % 2 = 0 OR id_l % 3 = 0",
        "pairs_setops": f"SELECT id_l, id_r, CASE WHEN (id_l + id_r) % 2 = 0 THEN 'even' ELSE 'odd' END AS part FROM ({PAIRS})",
        "doc_word_sets": f"WITH s AS (SELECT id, count(*) AS n, min({MARK.format('t')}) AS f, max({MARK.format('t')}) AS l FROM ({WORDS}) GROUP BY id) SELECT doc_id AS id, coalesce(n, 0) AS n, coalesce(f, 0) AS first, coalesce(l, 0) AS last FROM documents LEFT JOIN s ON s.id = doc_id",
        "doc_shingle_sets": f"WITH s AS (SELECT id, count(*) AS n, min({MARK.format('t')}) AS f, max({MARK.format('t')}) AS l FROM ({SHINGLES}) GROUP BY id) SELECT id, n, f AS first, l AS last FROM s",
        "pages_text": f"SELECT page_id, len({TOKENS.format('''regexp_replace(html, '<[^>]*>', ' ', 'g')''')}) AS tokens FROM pages",
        "name_edit_distance": "SELECT a.p_partkey AS k_l, b.p_partkey AS k_r, levenshtein(a.p_name, b.p_name) AS edits FROM part a JOIN part b ON a.p_partkey < b.p_partkey AND substr(a.p_name, 1, 6) = substr(b.p_name, 1, 6) AND abs(length(a.p_name) - length(b.p_name)) <= 3 WHERE levenshtein(a.p_name, b.p_name) <= 3",
        "string_funcs": "SELECT c_custkey, lower(trim(c_name)) AS low, substr(c_name, 1, 4) AS head, split_part(c_name, '#', 2) AS part, replace(c_name, 'Customer', 'C') AS short, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, length(c_name) AS n FROM customer",
        "md5_keys": f"SELECT doc_id, {MARK.format('''coalesce(text, '')''')} AS key FROM documents",
        "exact_hamming_bits": f"SELECT id, CAST(bit_count(f) AS BIGINT) AS ones, CAST((f >> 5) & 1 AS BIGINT) AS bit5, CAST((f >> 60) & 15 AS BIGINT) AS top FROM (SELECT id, CAST(f AS HUGEINT) AS f FROM ({SIGN}))",
        "array_set_ops": f"WITH t AS ({WORDS}), n AS (SELECT id, count(*) AS c FROM t GROUP BY id), p AS (SELECT a.id, count(*) AS k FROM t a JOIN t b ON a.t = b.t AND b.id = a.id + 1 GROUP BY 1) SELECT x.id AS id_l, coalesce(k, 0) AS \"both\", x.c + y.c - coalesce(k, 0) AS either, x.c - coalesce(k, 0) AS only_l, coalesce(k, 0) > 0 AS overlap FROM n x JOIN n y ON y.id = x.id + 1 LEFT JOIN p ON p.id = x.id",
        "explode_reps": "SELECT CAST(rep AS INTEGER) AS rep, CAST(sum(doc_id) AS BIGINT) AS ids, CAST(max(rep - 1) AS BIGINT) AS place FROM documents, range(1, 5) r(rep) GROUP BY rep",
        "sparse_map_cosine": f"WITH g AS (SELECT id, t, count(*) AS c FROM ({DOCS}) GROUP BY 1, 2), n AS (SELECT id, CAST(sum(c * c) AS DOUBLE) AS n FROM g GROUP BY id), p AS (SELECT a.id AS id_l, b.id AS id_r, CAST(sum(a.c * b.c) AS DOUBLE) AS d FROM g a JOIN g b ON a.t = b.t AND a.id < b.id GROUP BY 1, 2) SELECT id_l, id_r, round(d / sqrt(x.n * y.n), 6) AS cos FROM p JOIN n x ON x.id = id_l JOIN n y ON y.id = id_r WHERE round(d / sqrt(x.n * y.n), 6) >= 0.3",
        "events_props_json": "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n, min(event_id) AS first_event FROM events GROUP BY 1",
        "events_calendar": "SELECT CAST(date_trunc('day', ts) AS DATE) AS day, hour(ts) AS hour, dayofweek(ts) + 1 AS weekday, count(*) AS n FROM events GROUP BY 1, 2, 3",
        "events_tumbling": "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "events_sliding": "SELECT s AS start, count(*) AS n FROM (SELECT unnest([CAST(floor(epoch(ts) / 1800) AS BIGINT) * 1800, CAST(floor(epoch(ts) / 1800) AS BIGINT) * 1800 - 1800]) AS s FROM events) GROUP BY s",
        "events_session": "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1",
        "udf_l2_emb": f"{EMB_PAIRS} SELECT id_l, id_r, round(d, 6) AS dist FROM p WHERE d <= 1.2",
        "udaf_centroid": "WITH u AS (SELECT label, unnest(range(0, 64)) AS i, unnest(embedding) AS x FROM embeddings), m AS (SELECT label, i, avg(CAST(x AS DOUBLE)) AS m FROM u GROUP BY 1, 2), c AS (SELECT label, count(*) AS n FROM embeddings GROUP BY 1) SELECT label, round(sqrt(sum(m * m)), 5) AS centroid_norm, any_value(n) AS n FROM m JOIN c USING (label) GROUP BY label",
        "udtf_shingles": f"WITH s AS (SELECT doc_id, unnest(list_transform(range(1, greatest(len(w) - 1, 1)), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS t FROM (SELECT doc_id, {TOKENS.format('text')} AS w FROM documents) WHERE len(w) >= 3) SELECT doc_id, count(*) AS n, count(DISTINCT t) AS kinds FROM s GROUP BY 1",
        "leaf_kernel_docs": f"WITH f AS (SELECT f.id, f.f, source FROM ({FINGERS}) f JOIN documents ON doc_id = id) SELECT a.id AS id_l, b.id AS id_r, CAST(bit_count(xor(a.f, b.f)) AS BIGINT) AS dist FROM f a JOIN f b ON a.source = b.source AND a.id < b.id WHERE bit_count(xor(a.f, b.f)) <= 10",
        "sql_near_pairs": PAIRS,
        "subquery_dups": f"SELECT doc_id, n_chars FROM documents d WHERE doc_id IN (SELECT id_r FROM ({PAIRS})) AND n_chars > (SELECT avg(n_chars) FROM documents x WHERE x.lang = d.lang) AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)",
        "dedup_keep_longest": f"WITH c AS ({CLUSTERS}), d AS (SELECT doc_id, coalesce(cluster, doc_id) AS cluster, n_chars FROM documents LEFT JOIN c ON c.id = doc_id) SELECT doc_id, cluster, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY n_chars DESC, doc_id) AS place FROM d) WHERE place = 1",
        "near_dup_quality": f"SELECT quality, toxic, count(*) AS pairs, round(avg(dist), 6) AS mean_dist FROM ({PAIRS}) JOIN labels ON id_r = doc_id GROUP BY 1, 2",
        "exact_statistics": "SELECT lang, round(quantile_cont(n_chars, 0.5), 3) AS median, round(stddev_samp(n_chars), 3) AS spread, round(corr(n_chars, doc_id), 6) AS corr FROM documents GROUP BY 1",
    }


def streams() -> dict[str, str]:
    batch = surface()
    return {
        "stream_tumbling": batch["events_tumbling"],
        "stream_sliding": "SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([CAST(floor(epoch(ts) / 1800) AS BIGINT) * 1800, CAST(floor(epoch(ts) / 1800) AS BIGINT) * 1800 - 1800]) AS s FROM events) GROUP BY s, event_type",
        "stream_session": "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k",
        "stream_stream_interval": batch["events_interval_join"],
        "stream_late_rows": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1",
        "stream_dedup_watermark": "SELECT DISTINCT user_id, event_type FROM events",
        "stream_state_ttl": 'SELECT user_id AS key, count(*) AS "rows", count(*) - 1 AS most_before FROM events GROUP BY 1',
        "stream_upsert_index": 'SELECT CAST(tag AS INTEGER) AS tag, count(*) AS "rows", count(DISTINCT vec_id) AS points FROM embeddings, range(8) t(tag) GROUP BY tag',
    }


def oracle_sql() -> dict[str, str]:
    return {k: v for k, v in (core() | measures() | surface() | streams()).items() if v}
