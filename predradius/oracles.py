"""SQL for the same results, built from shared pieces."""

from __future__ import annotations

from .sources import SUITES

SEEDS = list(range(20))
SIZES = [1, 2, 4, 8, 16, 32, 64]


def _list(values: list[str]) -> str:
    return "[" + ", ".join(f"'{v}'" for v in values) + "]::VARCHAR[]"


def _co(suite: str) -> str:
    return "co(concept_id, all_of, any_of, pos) AS (VALUES " + ", ".join(f"('{c}', {_list(a)}, {_list(o)}, {i})" for i, (c, a, o) in enumerate(SUITES[suite])) + ")"


IT = {
    "w1": "it AS (SELECT p_partkey AS item_id, list_concat(string_split(p_name, ' '), ['type:' || p_type, p_brand]) AS toks FROM part)",
    "w2": "it AS (SELECT c_custkey AS item_id, [r_name, n_name, c_mktsegment] AS toks FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)",
}
HOLDS = "(list_has_all(toks, all_of) AND (len(any_of) = 0 OR list_has_any(toks, any_of)))"
SIGN = "2 * (((instr('0123456789abcdef', substr(md5(t), (i // 4 + 1)::INT, 1)) - 1) >> (3 - i % 4)::INT) & 1) - 1"
VEC = f"""sg AS (SELECT t, i, {SIGN} AS s FROM (SELECT DISTINCT unnest(toks) AS t FROM it UNION SELECT DISTINCT unnest(list_concat(all_of, any_of)) FROM co) CROSS JOIN range(128) r(i)),
iv AS (SELECT item_id, i, sum(s)::BIGINT AS v FROM (SELECT item_id, unnest(toks) AS t FROM it) JOIN sg USING (t) GROUP BY ALL),
cv AS (SELECT concept_id, i, sum(s)::BIGINT AS v FROM (SELECT concept_id, unnest(list_concat(all_of, any_of)) AS t FROM co) JOIN sg USING (t) GROUP BY ALL),
inn AS (SELECT item_id, sum(v * v)::BIGINT AS n1 FROM iv GROUP BY ALL), cnn AS (SELECT concept_id, sum(v * v)::BIGINT AS n2 FROM cv GROUP BY ALL),
di AS (SELECT concept_id, item_id, CASE WHEN n1 * n2 > 0 THEN 1 - d / sqrt(n1::DOUBLE * n2::DOUBLE) ELSE 1.0 END AS dist, {HOLDS} AS yes
  FROM (SELECT concept_id, item_id, sum(iv.v * cv.v)::BIGINT AS d FROM iv JOIN cv USING (i) GROUP BY ALL) JOIN inn USING (item_id) JOIN cnn USING (concept_id) JOIN it USING (item_id) JOIN co USING (concept_id))"""
TRUTH = f"tr AS (SELECT concept_id, count(*) FILTER (WHERE {HOLDS}) AS hits, count(*) AS total, count(*) FILTER (WHERE {HOLDS}) / count(*) AS truth FROM it CROSS JOIN co GROUP BY ALL)"
SAMPLE = f"hs AS (SELECT item_id, seed, row_number() OVER (PARTITION BY seed ORDER BY md5(seed || ':' || item_id), item_id)::INT AS slot FROM it CROSS JOIN (SELECT unnest({SEEDS})::INT AS seed))"
PROBED = """pr AS (SELECT seed, m, concept_id, max(k) AS k, max(n) AS n, coalesce(max(dist) FILTER (WHERE r = k + 1), 2.000001) AS radius FROM (
  SELECT *, row_number() OVER (PARTITION BY seed, m, concept_id ORDER BY dist, item_id) AS r, sum(yes::INT) OVER (PARTITION BY seed, m, concept_id)::BIGINT AS k, count(*) OVER (PARTITION BY seed, m, concept_id) AS n
  FROM hs JOIN (SELECT unnest([32, 64, 128])::INT AS m) ON slot <= m JOIN di USING (item_id)) GROUP BY ALL)"""
EST = "es AS (SELECT seed, m, concept_id, radius, count(*) FILTER (WHERE dist < radius) AS hits, count(*) AS total FROM pr JOIN di USING (concept_id) GROUP BY ALL)"
PROFILE = f"sp AS (SELECT seed, m, concept_id, count(*) FILTER (WHERE {HOLDS}) / count(*) AS estimate FROM hs JOIN (SELECT unnest({SIZES})::INT AS m) ON slot <= m JOIN it USING (item_id) CROSS JOIN co GROUP BY ALL)"
RUNS = """runs AS (SELECT 'probed' AS method, m, seed, concept_id, hits / total AS estimate, 0.9 AS latency FROM es UNION ALL SELECT 'profile', m, seed, concept_id, estimate, m * 1.0 FROM sp),
qe AS (SELECT method, m, seed, concept_id, estimate, latency, truth, greatest(greatest(estimate, 1 / total) / greatest(truth, 1 / total), greatest(truth, 1 / total) / greatest(estimate, 1 / total)) AS q FROM runs JOIN tr USING (concept_id))"""
QUERIES = """qu AS (SELECT query_id, n_filters, concept_id, pos, written FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY md5(query_id || ':' || concept_id), concept_id)::INT AS written
  FROM (SELECT q AS query_id, (2 + q // 100)::INT AS n_filters FROM range(300) r(q)) CROSS JOIN co) WHERE written <= n_filters)"""
MASKS = f"ma AS (SELECT mask, count(*) AS n FROM (SELECT item_id, sum(CASE WHEN {HOLDS} THEN 1::BIGINT << pos ELSE 0 END)::BIGINT AS mask FROM it CROSS JOIN co GROUP BY ALL) GROUP BY ALL)"
EST_ALL = """ea AS (SELECT method, m, seed, concept_id, estimate FROM runs UNION ALL SELECT 'perfect', 0, 0, concept_id, truth FROM tr UNION ALL SELECT 'written', 0, 0, concept_id, pos FROM co)"""
ORDERS = """od AS (SELECT *, row_number() OVER (PARTITION BY method, m, seed, query_id ORDER BY estimate, concept_id)::INT AS step FROM qu JOIN ea USING (concept_id) WHERE method <> 'written'
  UNION ALL SELECT *, written FROM qu JOIN ea USING (concept_id) WHERE method = 'written'),
nd AS (SELECT *, coalesce(sum(1::BIGINT << pos) OVER (PARTITION BY method, m, seed, query_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS need FROM od),
ns AS (SELECT need, coalesce(sum(n), 0)::BIGINT AS calls FROM (SELECT DISTINCT need FROM nd) LEFT JOIN ma ON (mask & need) = need GROUP BY ALL),
cc AS (SELECT method, m, seed, query_id, n_filters, sum(calls)::BIGINT AS calls FROM nd JOIN ns USING (need) GROUP BY ALL)"""
COST = """ov AS (SELECT c.method, c.m, c.seed, c.query_id, c.n_filters, c.n_filters * CASE c.method WHEN 'profile' THEN c.m * 1.0 WHEN 'probed' THEN 0.9 ELSE 0 END AS est_s, c.calls - p.calls AS plan_s
  FROM cc c JOIN cc p ON c.query_id = p.query_id AND p.method = 'perfect')"""
GROUPS = "gr AS (SELECT method, m, n_filters, seed, sum(est_s) AS est_s, sum(plan_s) AS plan_s, sum(est_s + plan_s) AS overhead FROM ov GROUP BY ALL), me AS (SELECT method, m, n_filters, avg(overhead) AS mean, stddev_samp(overhead) AS sd, count(*) AS runs FROM gr GROUP BY ALL)"

TOKENS = "hc AS (SELECT DISTINCT unnest(toks) AS concept_id FROM it)"
HELD = """hc AS (SELECT array_to_string(all_of, '&') AS concept_id, all_of FROM (SELECT DISTINCT unnest(list_concat(list_transform(toks, lambda t: [t]), list_transform(range(2, len(toks) + 1), lambda i: toks[1:i]))) AS all_of FROM it))"""
HELD_QUERIES = QUERIES.replace("CROSS JOIN co", "CROSS JOIN (SELECT concept_id, 0 AS pos FROM hc)")


def sql(suite: str, *parts: str) -> str:
    """The last part is the query, the others the tables it needs."""
    return "WITH " + ", ".join([IT[suite], _co(suite), *parts[:-1]]) + " " + parts[-1]


FULL = (VEC, TRUTH, SAMPLE, PROBED, EST, PROFILE, RUNS)
CHAIN = (*FULL, QUERIES, MASKS, EST_ALL, ORDERS, COST, GROUPS)


def method_oracles() -> dict[str, str]:
    found = {}
    for s, tag in (("w1", "part"), ("w2", "geo")):
        found |= {
            f"embed_{tag}": sql(s, VEC, "SELECT item_id, string_agg(v::VARCHAR, ',' ORDER BY i) AS vec, max(n1) AS norm2 FROM iv JOIN inn USING (item_id) GROUP BY item_id"),
            f"embed_concepts_{tag}": sql(s, HELD, f"hs AS (SELECT t, i, {SIGN} AS s FROM (SELECT DISTINCT unnest(all_of) AS t FROM hc) CROSS JOIN range(128) r(i))", "hv AS (SELECT concept_id, i, sum(s)::BIGINT AS v FROM (SELECT concept_id, unnest(all_of) AS t FROM hc) JOIN hs USING (t) GROUP BY ALL)",
                                         "SELECT concept_id, string_agg(v::VARCHAR, ',' ORDER BY i) AS vec, sum(v * v)::BIGINT AS norm2 FROM hv GROUP BY concept_id"),
            f"distance_matrix_{tag}": sql(s, VEC, "SELECT concept_id, item_id, round(dist, 9) AS dist, yes FROM di"),
            f"true_selectivity_{tag}": sql(s, TRUTH, "SELECT concept_id, hits, total, truth AS selectivity FROM tr"),
            f"fixed_radius_{tag}": sql(s, VEC, "SELECT concept_id, 0.5::DOUBLE AS radius, count(*) FILTER (WHERE dist < 0.5) AS hits, count(*) AS total FROM di GROUP BY ALL"),
            f"ball_precision_recall_{tag}": sql(s, VEC, "SELECT concept_id, count(*) FILTER (WHERE dist < 0.5 AND yes) AS found, count(*) FILTER (WHERE dist < 0.5 AND NOT yes) AS false_hits, count(*) FILTER (WHERE dist >= 0.5 AND yes) AS missed FROM di GROUP BY ALL"),
            f"hash_sample_{tag}": sql(s, SAMPLE, "SELECT seed, slot, item_id FROM hs WHERE slot <= 64"),
            f"probed_radius_{tag}": sql(s, VEC, SAMPLE, PROBED, "SELECT seed, m, concept_id, k, n, radius FROM pr"),
            f"probed_radius_zero_{tag}": sql(s, VEC, SAMPLE, PROBED, "SELECT seed, m, concept_id, radius FROM pr WHERE k = 0"),
            f"estimate_probed_{tag}": sql(s, VEC, SAMPLE, PROBED, EST, "SELECT seed, m, concept_id, hits, total, hits / total AS selectivity FROM es"),
            f"ideal_radius_{tag}": sql(s, VEC, "SELECT concept_id, max(k) AS k, max(n) AS n, coalesce(max(dist) FILTER (WHERE r = k + 1), 2.000001) AS radius FROM (SELECT *, row_number() OVER (PARTITION BY concept_id ORDER BY dist, item_id) AS r, sum(yes::INT) OVER (PARTITION BY concept_id)::BIGINT AS k, count(*) OVER (PARTITION BY concept_id) AS n FROM di) GROUP BY concept_id"),
            f"sample_profile_{tag}": sql(s, SAMPLE, PROFILE, "SELECT seed, m, concept_id, estimate FROM sp"),
            f"probe_share_{tag}": sql(s, VEC, SAMPLE, PROBED, "SELECT seed, m, concept_id, k / n AS estimate FROM pr"),
            f"precomputed_outcomes_{tag}": sql(s, TRUTH, "SELECT concept_id, CASE WHEN pos % 2 = 0 THEN truth END AS selectivity FROM co JOIN tr USING (concept_id)"),
            f"noisy_answers_{tag}": sql(s, f"SELECT concept_id, count(*) FILTER (WHERE yes <> flip) AS hits, count(*) FILTER (WHERE flip) AS flipped FROM (SELECT concept_id, {HOLDS} AS yes, substr(md5(concept_id || ':' || item_id), 1, 4) < '0ccc' AS flip FROM it CROSS JOIN co) GROUP BY ALL"),
            f"qerror_{tag}": sql(s, *FULL, "SELECT method, m, seed, concept_id, round(q, 9) AS q_error FROM qe"),
            f"qerror_summary_{tag}": sql(s, *FULL, "SELECT method, m, round(quantile_cont(q, 0.05), 6) AS p5, round(quantile_cont(q, 0.5), 6) AS p50, round(quantile_cont(q, 0.95), 6) AS p95, round(avg(latency), 6) AS latency_s FROM qe GROUP BY ALL"),
            f"parity_sample_{tag}": sql(s, *FULL, "pq AS (SELECT method, m, quantile_cont(q, 0.5) AS p50, quantile_cont(q, 0.95) AS p95 FROM qe GROUP BY ALL)", "SELECT b.m AS probe, min(a.m) AS sample FROM pq b LEFT JOIN pq a ON a.method = 'profile' AND a.p50 <= b.p50 AND a.p95 <= b.p95 WHERE b.method = 'probed' GROUP BY ALL"),
            f"truth_{tag}": sql(s, f"SELECT concept_id, item_id, {HOLDS} AS yes FROM it CROSS JOIN co"),
            f"radius_for_count_{tag}": sql(s, VEC, "SELECT concept_id, 10 AS k, count(*) AS n, coalesce(max(dist) FILTER (WHERE r = 11), 2.000001) AS radius FROM (SELECT *, row_number() OVER (PARTITION BY concept_id ORDER BY dist, item_id) AS r FROM di) GROUP BY concept_id"),
            f"qerror_zero_truth_{tag}": sql(s, *FULL, "SELECT method, m, truth = 0 AS truth_zero, count(*) AS n, round(quantile_cont(q, 0.5), 6) AS p50 FROM qe GROUP BY ALL"),
            f"order_ties_{tag}": sql(s, *FULL, "SELECT a.method, a.m, count(*) AS ties FROM runs a JOIN runs b ON a.method = b.method AND a.m = b.m AND a.seed = b.seed AND a.concept_id < b.concept_id AND a.estimate = b.estimate GROUP BY ALL"),
            f"endtoend_cost_{tag}": sql(s, *CHAIN, "SELECT method, m, n_filters, seed, round(sum(n_filters * CASE method WHEN 'profile' THEN m * 1.0 WHEN 'probed' THEN 0.9 ELSE 0 END + calls), 6) AS seconds FROM cc GROUP BY ALL"),
            f"profile_reuse_{tag}": sql(s, *CHAIN, "SELECT m, n_filters, round(avg(overhead), 6) AS mean, round(avg(overhead) - 100.0 * m, 6) AS mean_reused FROM gr WHERE method = 'profile' GROUP BY m, n_filters"),
            f"random_queries_{tag}": sql(s, TOKENS, HELD_QUERIES, "SELECT query_id, n_filters, concept_id, written FROM qu"),
            f"order_filters_{tag}": sql(s, *CHAIN, "SELECT method, m, seed, query_id, concept_id, step FROM od WHERE method <> 'written'"),
            f"chain_calls_{tag}": sql(s, *CHAIN, "SELECT method, m, seed, query_id, n_filters, calls FROM cc"),
            f"overhead_{tag}": sql(s, *CHAIN, "SELECT method, m, n_filters, seed, round(overhead, 6) AS overhead FROM gr"),
            f"overhead_split_{tag}": sql(s, *CHAIN, "SELECT method, m, n_filters, round(avg(est_s), 6) AS est_part, round(avg(plan_s), 6) AS plan_part FROM gr GROUP BY ALL"),
            f"overhead_ci_{tag}": sql(s, *CHAIN, "SELECT method, m, n_filters, round(mean, 6) AS mean, round(mean - 2.093 * sd / sqrt(runs), 6) AS low, round(mean + 2.093 * sd / sqrt(runs), 6) AS high FROM me WHERE runs > 1"),
            f"best_config_{tag}": sql(s, *CHAIN, "SELECT method, n_filters, m, round(mean, 6) AS mean FROM (SELECT *, row_number() OVER (PARTITION BY method, n_filters ORDER BY mean, m) AS r FROM me) WHERE r = 1"),
            f"overhead_reduction_{tag}": sql(s, *CHAIN, "SELECT n_filters, round(1 - min(mean) FILTER (WHERE method = 'probed') / min(mean) FILTER (WHERE method = 'profile'), 6) AS reduction FROM me GROUP BY ALL"),
            f"order_inversions_{tag}": sql(s, *CHAIN, "SELECT a.method, a.m, count(*) AS pairs, sum((ta.truth > tb.truth)::INT)::BIGINT AS inverted FROM od a JOIN od b ON a.method = b.method AND a.m = b.m AND a.seed = b.seed AND a.query_id = b.query_id AND a.step < b.step JOIN tr ta ON ta.concept_id = a.concept_id JOIN tr tb ON tb.concept_id = b.concept_id WHERE a.method <> 'written' GROUP BY ALL"),
        }
    return found | {
        "probe_configs_memory": sql("w1", "SELECT n::INT AS n, ratio::DOUBLE AS ratio, round(n * kept / tokens, 6)::DOUBLE AS full_states, round(n * kept / tokens * 300000000, 0)::DOUBLE AS bytes FROM (SELECT n, ratio, sum(ceil((1 - ratio) * len(toks)))::BIGINT AS kept, sum(len(toks))::BIGINT AS tokens FROM it CROSS JOIN (VALUES (128, 0.9), (64, 0.8), (32, 0.6)) t(n, ratio) GROUP BY ALL)"),
        "synopsis_bytes": "SELECT count(*) AS items, count(*) * 4608 AS bytes FROM part",
        "ball_count_vectors": "WITH a AS (SELECT e.vec_id AS anchor, e.embedding AS p, r.radius FROM embeddings e CROSS JOIN (SELECT unnest([0.6, 0.7, 0.8, 0.9])::DOUBLE AS radius) r WHERE e.vec_id % 20 = 0), x AS (SELECT anchor, radius, 1 - list_sum(list_transform(list_zip(embedding, p), lambda z: z[1]::DOUBLE * z[2]::DOUBLE)) / sqrt(list_sum(list_transform(embedding, lambda z: z::DOUBLE * z)) * list_sum(list_transform(p, lambda z: z::DOUBLE * z))) AS dist FROM embeddings CROSS JOIN a) SELECT anchor, radius, count(*) FILTER (WHERE dist < radius) AS hits, count(*) AS total FROM x GROUP BY ALL",
        "hist_equiwidth": "WITH b AS (SELECT min(p_retailprice) AS lo, max(p_retailprice) AS hi FROM part) SELECT least(19, floor((p_retailprice - lo) / (hi - lo) * 20))::INT AS bucket, count(*) AS n FROM part, b GROUP BY ALL",
    }
