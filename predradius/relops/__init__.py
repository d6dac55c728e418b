"""Surrounding operators: one statement each, run by Spark SQL over the tables it names; the same statement is the oracle unless another is given."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import shared_folder, table

REV = "round(sum(l_extendedprice * (1 - l_discount)), 2)"
#: key -> (tables, statement, statement for the oracle or None for the same)
STATEMENTS: dict[str, tuple[str, str, str | None]] = {
    "scan_parquet": ("part", "SELECT p_partkey, p_size FROM part WHERE p_size > 40", None),
    "project_filter": ("part", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'S' WHEN p_size < 30 THEN 'M' ELSE 'L' END AS band FROM part WHERE p_brand IN ('Brand#1', 'Brand#13') AND p_retailprice BETWEEN 900 AND 1500", None),
    "like_rlike": ("part", "SELECT p_partkey FROM part WHERE p_name LIKE '%ring' AND regexp_like(p_name, '^(red|blue)')", "SELECT p_partkey FROM part WHERE p_name LIKE '%ring' AND regexp_matches(p_name, '^(red|blue)')"),
    "null_safe_eq": ("documents labels", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.toxic <=> NULL", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.toxic IS NOT DISTINCT FROM NULL"),
    "join_left": ("documents labels", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id", None),
    "join_right": ("documents labels", "SELECT l.doc_id, d.lang FROM documents d RIGHT JOIN labels l ON d.doc_id = l.doc_id", None),
    "join_full": ("supplier customer", "SELECT s.s_suppkey, c.c_custkey FROM supplier s FULL JOIN customer c ON s.s_suppkey = c.c_custkey", None),
    "join_cross": ("region", "SELECT a.r_name AS a, b.r_name AS b FROM region a CROSS JOIN region b", None),
    "join_semi": ("documents labels", "SELECT d.doc_id FROM documents d LEFT SEMI JOIN labels l ON d.doc_id = l.doc_id", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)"),
    "join_anti": ("documents labels", "SELECT d.doc_id FROM documents d LEFT ANTI JOIN labels l ON d.doc_id = l.doc_id", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)"),
    "join_interval": ("events", "SELECT e.event_id AS a, c.event_id AS b FROM events e JOIN events c ON e.user_id = c.user_id AND e.event_id <> c.event_id AND c.ts > e.ts AND c.ts <= e.ts + INTERVAL 10 MINUTE WHERE e.event_type = 'click'", None),
    "join_asof": ("events", "SELECT event_id, prior FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END, true) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prior FROM events) WHERE event_type = 'purchase'",
                  "SELECT event_id, prior FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prior FROM events) WHERE event_type = 'purchase'"),
    "join_range_bucket": ("part", "SELECT b.lo, count(*) AS n FROM part p JOIN (SELECT CAST(id * 10 AS INT) AS lo, CAST(id * 10 + 10 AS INT) AS hi FROM range(6)) b ON p.p_size >= b.lo AND p.p_size < b.hi GROUP BY b.lo", "SELECT b.lo, count(*) AS n FROM part p JOIN (SELECT CAST(range * 10 AS INT) AS lo, CAST(range * 10 + 10 AS INT) AS hi FROM range(6)) b ON p.p_size >= b.lo AND p.p_size < b.hi GROUP BY b.lo"),
    "hybrid_revenue": ("lineitem part orders", f"SELECT year(o_orderdate) AS y, {REV} AS revenue FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey WHERE p_name LIKE '%ring%' GROUP BY 1", None),
    "agg_basic": ("lineitem", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 6) AS d, round(stddev_samp(l_quantity), 6) AS s FROM lineitem GROUP BY l_returnflag, l_linestatus", None),
    "agg_distinct": ("lineitem", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY l_returnflag", None),
    "agg_percentile": ("lineitem", "SELECT l_returnflag, round(percentile(l_extendedprice, 0.5), 4) AS p50, round(percentile(l_extendedprice, 0.95), 4) AS p95 FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS p50, round(quantile_cont(l_extendedprice, 0.95), 4) AS p95 FROM lineitem GROUP BY l_returnflag"),
    "agg_minmax_by": ("part", "SELECT p_type, max_by(p_partkey, struct(p_retailprice, p_partkey)) AS top FROM part GROUP BY p_type", "SELECT p_type, arg_max(p_partkey, row(p_retailprice, p_partkey)) AS top FROM part GROUP BY p_type"),
    "agg_regression": ("lineitem", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem GROUP BY l_returnflag", None),
    "agg_rollup": ("part", "SELECT p_brand, p_type, count(*) AS n, CAST(grouping(p_brand) * 2 + grouping(p_type) AS INT) AS g FROM part GROUP BY ROLLUP (p_brand, p_type)", None),
    "agg_cube": ("part", "SELECT p_brand, p_type, count(*) AS n, CAST(grouping(p_brand) * 2 + grouping(p_type) AS INT) AS g FROM part GROUP BY CUBE (p_brand, p_type)", None),
    "agg_grouping_sets": ("part", "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())", None),
    "pivot_report": ("events", "SELECT * FROM (SELECT user_id, event_type FROM events) PIVOT (count(*) FOR event_type IN ('click' AS click, 'purchase' AS purchase))", "SELECT user_id, nullif(count(*) FILTER (WHERE event_type = 'click'), 0) AS click, nullif(count(*) FILTER (WHERE event_type = 'purchase'), 0) AS purchase FROM events GROUP BY user_id"),
    "unpivot_report": ("part", "SELECT p_partkey, name, val FROM (SELECT p_partkey, CAST(p_size AS DOUBLE) AS size, p_retailprice AS price FROM part) UNPIVOT (val FOR name IN (size, price))", "SELECT p_partkey, 'size' AS name, CAST(p_size AS DOUBLE) AS val FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part"),
    "win_rank": ("part", "SELECT p_partkey, rank() OVER (PARTITION BY p_type ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_type ORDER BY p_size) AS d, row_number() OVER (PARTITION BY p_type ORDER BY p_size, p_partkey) AS n FROM part", None),
    "win_ntile": ("part", "SELECT p_partkey, ntile(7) OVER (PARTITION BY p_type ORDER BY p_retailprice, p_partkey) AS b FROM part", None),
    "win_cume_dist": ("part", "SELECT p_partkey, round(cume_dist() OVER (PARTITION BY p_type ORDER BY p_size), 9) AS c, round(percent_rank() OVER (PARTITION BY p_type ORDER BY p_size), 9) AS p FROM part", None),
    "win_lag": ("events", "SELECT event_id, lag(event_id) OVER w AS a, lead(event_id) OVER w AS b, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", None),
    "win_rows_frame": ("orders", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS s FROM orders", None),
    "win_range_frame": ("events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events", None),
    "topk_per_group": ("part", "SELECT p_type, p_partkey FROM (SELECT p_type, p_partkey, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3", None),
    "sort_multi": ("part", "SELECT p_partkey, p_size FROM part ORDER BY p_size DESC, p_partkey LIMIT 50", None),
    "set_union": ("part", "SELECT p_partkey FROM part WHERE p_size < 10 UNION SELECT p_partkey FROM part WHERE p_brand = 'Brand#1'", None),
    "set_intersect": ("part", "SELECT p_partkey FROM part WHERE p_size < 10 INTERSECT SELECT p_partkey FROM part WHERE p_brand = 'Brand#1'", None),
    "set_except": ("part", "SELECT p_partkey FROM part WHERE p_size < 10 EXCEPT SELECT p_partkey FROM part WHERE p_brand = 'Brand#1'", None),
    "set_except_all": ("part", "SELECT p_size FROM part EXCEPT ALL SELECT p_size FROM part WHERE p_brand = 'Brand#1'", None),
    "fn_string": ("part", "SELECT p_partkey, upper(p_name) AS u, concat_ws('-', p_brand, p_type) AS c, translate(p_name, 'aeiou', '12345') AS t, instr(p_name, ' ') AS i, levenshtein(p_name, 'red ring') AS l FROM part", None),
    "fn_regex": ("documents", "SELECT doc_id, size(regexp_extract_all(text, '[0-9]+', 0)) AS n FROM documents", "SELECT doc_id, len(regexp_extract_all(text, '[0-9]+'))::INT AS n FROM documents"),
    "fn_hash": ("documents", "SELECT doc_id, md5(text) AS h, sha2(text, 256) AS s FROM documents", "SELECT doc_id, md5(text) AS h, sha256(text) AS s FROM documents"),
    "fn_date": ("orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS t, datediff(DATE '2000-01-01', CAST(o_orderdate AS DATE)) AS d FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS t, date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') AS d FROM orders"),
    "fn_math": ("part", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS s, round(ln(p_retailprice), 6) AS l, greatest(p_size, 10) AS g, p_size % 7 AS m, sign(p_size - 25.0D) AS z FROM part", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS s, round(ln(p_retailprice), 6) AS l, greatest(p_size, 10) AS g, p_size % 7 AS m, sign(p_size - 25.0)::DOUBLE AS z FROM part"),
    "fn_bits": ("part", "SELECT p_partkey, p_size & 12 AS a, p_size | 3 AS o, bit_count(p_size) AS c, shiftright(p_size, 1) AS r FROM part", "SELECT p_partkey, p_size & 12 AS a, p_size | 3 AS o, bit_count(p_size) AS c, p_size >> 1 AS r FROM part"),
    "fn_json": ("events", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events"),
    "fn_array_hof": ("part", "SELECT p_partkey, array_join(transform(split(p_name, ' '), x -> upper(x)), '+') AS u, exists(split(p_name, ' '), x -> x = 'ring') AS e FROM part", "SELECT p_partkey, array_to_string(list_transform(string_split(p_name, ' '), lambda x: upper(x)), '+') AS u, list_contains(string_split(p_name, ' '), 'ring') AS e FROM part"),
    "fn_map": ("part", "SELECT p_partkey, element_at(map_from_arrays(array('brand', 'type'), array(p_brand, p_type)), 'type') AS t FROM part", "SELECT p_partkey, p_type AS t FROM part"),
    "fn_struct": ("part", "SELECT p_partkey, s.b AS b, s.t AS t FROM (SELECT p_partkey, named_struct('b', p_brand, 't', p_type) AS s FROM part)", "SELECT p_partkey, p_brand AS b, p_type AS t FROM part"),
    "fn_url": ("pages", "SELECT page_id, parse_url(url, 'HOST') AS host FROM pages", "SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM pages"),
    "html_text_filter": ("pages", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '')) AS n FROM pages WHERE html LIKE '%<a %'", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages WHERE html LIKE '%<a %'"),
    "subq_scalar": ("orders", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)", None),
    "subq_exists": ("orders customer", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)", None),
    # Spark turns ORDER BY .. LIMIT 1 of a correlated subquery into first() over sorted rows, and a shuffle between them loses the order; a rank does not depend on it.
    "lateral_topk": ("customer orders", "SELECT c.c_custkey, t.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC NULLS LAST, o_orderkey NULLS LAST) AS r FROM orders) o WHERE o.o_custkey = c.c_custkey AND o.r = 1) t",
                     "SELECT c.c_custkey, t.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM orders o WHERE o.o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t"),
    "salted_agg": ("documents", "SELECT source, sum(n) AS n FROM (SELECT source, doc_id % 16 AS salt, count(*) AS n FROM documents GROUP BY source, doc_id % 16) GROUP BY source", "SELECT source, count(*) AS n FROM documents GROUP BY source"),
}

JOINED = "SELECT l_orderkey, l_linenumber, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity < 5"


def statement(key: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    names, text, _ = STATEMENTS[key]
    for name in names.split():
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark.sql(text)


def hinted(hint: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", "p_brand").hint(hint)
    line = table(spark, sf_dir, "lineitem").filter("l_quantity < 5").select("l_orderkey", "l_linenumber", "l_partkey")
    return line.join(part, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "p_brand")


def round_trip(kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """nation written as another format and read again with its schema."""
    import uuid

    nation = table(spark, sf_dir, "nation")
    path = f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"
    nation.write.format(kind).save(path)
    return spark.read.schema(nation.schema).format(kind).load(path)


def relational_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {k: partial(statement, k) for k in STATEMENTS}
    found |= {f"join_{name}": partial(hinted, hint) for name, hint in (("broadcast", "broadcast"), ("merge", "merge"), ("shuffle_hash", "shuffle_hash"))}
    from . import semantic

    return found | {f"roundtrip_{k}": partial(round_trip, k) for k in ("csv", "json", "orc")} | semantic.QUERIES


def relational_oracles() -> dict[str, str]:
    found = {k: other or text for k, (_, text, other) in STATEMENTS.items()}
    found |= {f"join_{name}": JOINED for name in ("broadcast", "merge", "shuffle_hash")}
    from . import semantic

    return found | {f"roundtrip_{k}": "SELECT * FROM nation" for k in ("csv", "json", "orc")} | semantic.oracles()
