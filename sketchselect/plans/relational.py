"""Relational operators around the methods, as SQL over the given tables.

Each entry is the text for Spark and, where the dialects differ, the text for the check
engine. ``{table}`` names a table.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sketchselect.schema import TABLES
from sketchselect.tables import load

SAME = None
#: key -> (Spark SQL, other SQL or SAME)
SQL: dict[str, tuple[str, str | None]] = {}


def _add(name: str, spark: str, other: str | None = SAME) -> None:
    SQL[name] = (spark, other)


# ---- scans: columns by name, timestamps as microseconds, arrays as text
for _table, _schema in TABLES.items():
    _spark, _duck = [], []
    for _f in _schema.fields:
        kind = _f.dataType.typeName()
        if kind == "timestamp":
            _spark.append(f"unix_micros({_f.name}) AS {_f.name}")
            _duck.append(f"epoch_us({_f.name}) AS {_f.name}")
        elif kind == "array":
            _spark.append(f"size({_f.name}) AS dims, round(aggregate({_f.name}, 0D, (s, x) -> s + x), 4) AS total")
            _duck.append(f"CAST(len({_f.name}) AS INTEGER) AS dims, round(list_sum(list_transform({_f.name}, lambda x: x::DOUBLE)), 4) AS total")
        else:
            _spark.append(_f.name)
            _duck.append(_f.name)
    _add(f"scan_{_table}", f"SELECT {', '.join(_spark)} FROM {{{_table}}}", f"SELECT {', '.join(_duck)} FROM {{{_table}}}")

# ---- filters and projections
_add("filter_between", "SELECT l_orderkey, l_linenumber, l_quantity FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 20 AND l_discount > 0.05")
_add("filter_in", "SELECT o_orderkey, o_orderpriority FROM {orders} WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice > 1000")
_add("filter_like", "SELECT p_partkey, p_type FROM {part} WHERE p_type LIKE '%A%' AND p_name NOT LIKE 'x%'")
_add("filter_rlike", "SELECT url FROM {pages} WHERE url RLIKE '/en/[0-9]+'", "SELECT url FROM {pages} WHERE regexp_matches(url, '/en/[0-9]+')")
_add("filter_null", "SELECT d.doc_id FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality IS NULL")
_add("filter_case", "SELECT doc_id, CASE WHEN quality = 1 AND toxic = 0 THEN 'keep' WHEN toxic = 1 THEN 'toxic' ELSE 'junk' END AS rule FROM {labels}")
_add(
    "filter_hash",
    "SELECT doc_id FROM {documents} WHERE pmod(CAST(conv(substring(md5(text), 1, 15), 16, 10) AS BIGINT), 10) < 8",
    "SELECT doc_id FROM {documents} WHERE CAST('0x' || substr(md5(text), 1, 15) AS BIGINT) % 10 < 8",
)
_add("label_rules", "SELECT doc_id, CAST(lang = 'en' AS INT) AS is_en, CAST(source = 'src0' AS INT) AS is_src0 FROM {documents}")
_add("active_filter", "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) > 5")

# ---- joins
_add("join_inner", "SELECT d.doc_id, d.lang, l.quality FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id")
_add("join_left", "SELECT c.c_custkey, count(o.o_orderkey) AS n FROM {customer} c LEFT JOIN {orders} o ON c.c_custkey = o.o_custkey GROUP BY c.c_custkey")
_add("join_right", "SELECT n.n_name, count(s.s_suppkey) AS n FROM {supplier} s RIGHT JOIN {nation} n ON s.s_nationkey = n.n_nationkey GROUP BY n.n_name")
_add(
    "join_full_est_true",
    """SELECT coalesce(a.p, b.p) AS p, a.n AS low, b.n AS high FROM
       (SELECT l_partkey AS p, count(*) AS n FROM {lineitem} WHERE l_quantity < 3 GROUP BY l_partkey) a FULL OUTER JOIN
       (SELECT l_partkey AS p, count(*) AS n FROM {lineitem} WHERE l_quantity > 48 GROUP BY l_partkey) b ON a.p = b.p""",
)
_TOP = "SELECT l_partkey FROM {lineitem} GROUP BY l_partkey ORDER BY sum(CAST(l_quantity AS BIGINT)) DESC, l_partkey LIMIT 50"
_add("join_semi_topk", f"SELECT p_partkey, p_brand FROM {{part}} LEFT SEMI JOIN ({_TOP}) t ON p_partkey = l_partkey", f"SELECT p_partkey, p_brand FROM {{part}} SEMI JOIN ({_TOP}) t ON p_partkey = l_partkey")
_add("join_anti_orders", "SELECT c_custkey FROM {customer} LEFT ANTI JOIN (SELECT o_custkey FROM {orders} WHERE o_totalprice > 200000) o ON c_custkey = o_custkey", "SELECT c_custkey FROM {customer} ANTI JOIN (SELECT o_custkey FROM {orders} WHERE o_totalprice > 200000) o ON c_custkey = o_custkey")
_add("join_cross_rows", "SELECT r.r_name, j.j FROM {region} r CROSS JOIN (SELECT explode(sequence(0, 4)) AS j) j", "SELECT r.r_name, CAST(j.j AS INTEGER) AS j FROM {region} r CROSS JOIN range(5) j(j)")
_add("join_self_pairs", "SELECT a.n_name AS a, b.n_name AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
_add("join_broadcast_topk", f"SELECT /*+ BROADCAST(t) */ l_orderkey, l_linenumber FROM {{lineitem}} JOIN ({_TOP.replace('l_partkey', 'l_partkey', 1)}) t USING (l_partkey)", f"SELECT l_orderkey, l_linenumber FROM {{lineitem}} JOIN ({_TOP}) t USING (l_partkey)")
_MERGE = "o_orderkey, l_linenumber FROM {orders} o JOIN {lineitem} l ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F'"
_add("join_merge_hint", f"SELECT /*+ MERGE(l) */ {_MERGE}", f"SELECT {_MERGE}")
_add("join_shuffle_hash", f"SELECT /*+ SHUFFLE_HASH(l) */ {_MERGE}", f"SELECT {_MERGE}")
_add("join_range_bins", "SELECT p_partkey, b.bin FROM {part} JOIN (VALUES (0, 0, 1000), (1, 1000, 1500), (2, 1500, 99999)) b(bin, lo, hi) ON p_retailprice >= b.lo AND p_retailprice < b.hi")
_add("join_theta", "SELECT a.r_name AS a, b.r_name AS b FROM {region} a JOIN {region} b ON a.r_regionkey < b.r_regionkey")
_add(
    "join_asof_event",
    """SELECT event_id, last_view FROM (
         SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END, true) OVER
           (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM {events})
       WHERE event_type = 'purchase'""",
    """SELECT event_id, last_view FROM (
         SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER
           (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM {events})
       WHERE event_type = 'purchase'""",
)
_add("join_interval", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM {events} v JOIN {events} p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
_add("join_nullsafe", "SELECT a.doc_id FROM (SELECT doc_id, nullif(quality, 0) AS q FROM {labels}) a JOIN (SELECT CAST(NULL AS INT) AS q) b ON a.q <=> b.q", "SELECT a.doc_id FROM (SELECT doc_id, nullif(quality, 0) AS q FROM {labels}) a JOIN (SELECT CAST(NULL AS INT) AS q) b ON a.q IS NOT DISTINCT FROM b.q")
_add(
    "join_lateral_top",
    "SELECT n_name, t.c_custkey, t.c_acctbal FROM {nation} n, LATERAL (SELECT c_custkey, c_acctbal FROM {customer} c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) t",
)
_STAR = "SELECT r_name, p_brand, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {part} ON l_partkey = p_partkey JOIN {supplier} ON l_suppkey = s_suppkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name, p_brand"
_add("join_star", _STAR)

# ---- aggregation
_add("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_discount), 6) AS mean, min(l_tax) AS low, max(l_tax) AS high FROM {lineitem} WHERE l_shipdate <= TIMESTAMP '1998-09-02 00:00:00' GROUP BY l_returnflag, l_linestatus")
_add("agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM {orders} GROUP BY o_orderpriority")
_add("agg_count_if", "SELECT lang, count_if(n_chars > 1000) AS long_texts FROM {documents} GROUP BY lang", "SELECT lang, CAST(count_if(n_chars > 1000) AS BIGINT) AS long_texts FROM {documents} GROUP BY lang")
_add("agg_filter_clause", "SELECT lang, count(*) FILTER (WHERE source = 'src0') AS n0 FROM {documents} GROUP BY lang")
_SETS = "SELECT lang, quality, toxic, count(*) AS n FROM {{documents}} JOIN {{labels}} USING (doc_id) GROUP BY {}"
_add("cube_labels", _SETS.format("CUBE (lang, quality, toxic)"))
_add("rollup_labels", _SETS.format("ROLLUP (lang, quality, toxic)"))
_add("grouping_sets_labels", _SETS.format("GROUPING SETS ((lang, quality), (lang, toxic), (quality, toxic), ())").replace("lang, quality, toxic, count", "lang, quality, toxic, count"))
_add(
    "pivot_lang",
    "SELECT * FROM (SELECT source, lang FROM {documents}) PIVOT (count(*) FOR lang IN ('de' AS de, 'en' AS en, 'es' AS es, 'fr' AS fr))",
    "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM {documents} GROUP BY source",
)
_add(
    "unpivot_stats",
    "SELECT name, value FROM (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(max(n_chars) AS DOUBLE) AS longest FROM {documents}) UNPIVOT (value FOR name IN (n, longest))",
)
_add("agg_percentiles", "SELECT l_returnflag, round(percentile(l_quantity, 0.25), 6) AS q1, round(percentile(l_quantity, 0.9), 6) AS q9 FROM {lineitem} GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(quantile_cont(l_quantity, 0.9), 6) AS q9 FROM {lineitem} GROUP BY l_returnflag")
_add("agg_median", "SELECT event_type, round(median(value), 6) AS mid FROM {events} GROUP BY event_type")
_add("agg_mode", "SELECT lang, max(n_chars) AS longest, max_by(doc_id, struct(n_chars, -doc_id)) AS longest_id FROM {documents} GROUP BY lang", "SELECT lang, max(n_chars) AS longest, arg_max(doc_id, (n_chars, -doc_id)) AS longest_id FROM {documents} GROUP BY lang")
_add("agg_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r FROM {lineitem}")
_add("agg_regr", "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) AS base, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2 FROM {lineitem}")
_add("agg_stddev", "SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 4) AS var FROM {events} GROUP BY event_type")
_add("agg_max_by", "SELECT user_id, max_by(event_id, struct(ts, event_id)) AS newest FROM {events} GROUP BY user_id", "SELECT user_id, arg_max(event_id, (ts, event_id)) AS newest FROM {events} GROUP BY user_id")
_add("agg_bool", "SELECT doc_id % 10 AS tenth, bool_and(quality = 1) AS every, bool_or(toxic = 1) AS some FROM {labels} GROUP BY doc_id % 10")
_add("agg_bitxor", "SELECT lang, bit_xor(doc_id) AS mark, bit_or(doc_id) AS any_bits FROM {documents} GROUP BY lang")
_add("agg_listagg", "SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM {nation} GROUP BY n_regionkey", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM {nation} GROUP BY n_regionkey")
_add("agg_having", "SELECT l_partkey, sum(CAST(l_quantity AS BIGINT)) AS q FROM {lineitem} GROUP BY l_partkey HAVING sum(CAST(l_quantity AS BIGINT)) > 900", "SELECT l_partkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM {lineitem} GROUP BY l_partkey HAVING sum(CAST(l_quantity AS BIGINT)) > 900")

# ---- windows
_W = "PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey"
_add("win_row_number", f"SELECT c_custkey, row_number() OVER ({_W}) AS rn FROM {{customer}}", f"SELECT c_custkey, CAST(row_number() OVER ({_W}) AS INTEGER) AS rn FROM {{customer}}")
_add("win_rank", "SELECT l_orderkey, l_linenumber, rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS r FROM {lineitem}", "SELECT l_orderkey, l_linenumber, CAST(rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS INTEGER) AS r FROM {lineitem}")
_add("win_dense_rank", "SELECT l_orderkey, l_linenumber, dense_rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS r FROM {lineitem}", "SELECT l_orderkey, l_linenumber, CAST(dense_rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS INTEGER) AS r FROM {lineitem}")
_add("win_percent_rank", f"SELECT c_custkey, round(percent_rank() OVER ({_W}), 6) AS r FROM {{customer}}")
_add("win_cume_dist", f"SELECT c_custkey, round(cume_dist() OVER ({_W}), 6) AS r FROM {{customer}}")
_add("win_ntile", f"SELECT c_custkey, ntile(5) OVER ({_W}) AS r FROM {{customer}}", f"SELECT c_custkey, CAST(ntile(5) OVER ({_W}) AS INTEGER) AS r FROM {{customer}}")
_E = "PARTITION BY user_id ORDER BY ts, event_id"
_add("win_lag", f"SELECT event_id, lag(event_id, 1) OVER ({_E}) AS before FROM {{events}}")
_add("win_lead", f"SELECT event_id, lead(event_id, 2, -1) OVER ({_E}) AS after FROM {{events}}", f"SELECT event_id, lead(event_id, 2, -1::BIGINT) OVER ({_E}) AS after FROM {{events}}")
_ALL = "ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING"
_add("win_first_last", f"SELECT event_id, first_value(event_id) OVER ({_E} {_ALL}) AS f, last_value(event_id) OVER ({_E} {_ALL}) AS l FROM {{events}}")
_add("win_nth", f"SELECT event_id, nth_value(event_id, 2) OVER ({_E} {_ALL}) AS second FROM {{events}}")
_add("win_rows_frame", f"SELECT event_id, round(avg(value) OVER ({_E} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 5) AS mean3 FROM {{events}}")
_add("win_range_time", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM {events}")
_add("win_running", f"SELECT event_id, round(sum(value) OVER ({_E} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS total FROM {{events}}")
_add("win_topk_per_lang", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS rn FROM {documents}) WHERE rn <= 5")

# ---- sort, limit, top-k
_add("sort_global", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey")
_add("sort_multi_nulls", "SELECT doc_id, nullif(toxic, 0) AS t FROM {labels} ORDER BY t NULLS LAST, doc_id DESC")
_add("limit_offset", "SELECT o_orderkey FROM {orders} ORDER BY o_totalprice, o_orderkey LIMIT 20 OFFSET 10")
_add("topk_global", "SELECT p_partkey, p_retailprice FROM {part} ORDER BY p_retailprice DESC, p_partkey LIMIT 25")
_add("topk_per_class", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM {part}) WHERE r <= 3")

# ---- set operations
_A, _B = "SELECT c_nationkey AS k FROM {customer} WHERE c_acctbal > 5000", "SELECT s_nationkey AS k FROM {supplier} WHERE s_acctbal > 6000"
for _name, _op in {"union_all": "UNION ALL", "union": "UNION", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}.items():
    _add(f"set_{_name}", f"{_A} {_op} {_B}")
_add("set_distinct", "SELECT DISTINCT lang, source FROM {documents}")

# ---- strings
_add("str_case", "SELECT p_partkey, lower(p_brand) AS l, upper(p_name) AS u, initcap('a' || lower(p_mfgr)) AS i FROM (SELECT *, p_brand AS p_mfgr FROM {part})", "SELECT p_partkey, lower(p_brand) AS l, upper(p_name) AS u, 'A' || lower(p_brand) AS i FROM {part}")
_add("str_trim_pad", "SELECT n_nationkey, trim('  ' || n_name || ' ') AS t, lpad(n_name, 12, '*') AS l, rpad(n_name, 4, '-') AS r FROM {nation}")
_add("str_split", "SELECT n_nationkey, split(n_name, 'A')[0] AS head, size(split(n_name, 'A')) AS parts FROM {nation}", "SELECT n_nationkey, string_split(n_name, 'A')[1] AS head, CAST(len(string_split(n_name, 'A')) AS INTEGER) AS parts FROM {nation}")
_add("str_regex", "SELECT page_id, regexp_extract(url, '^(https?)://([^/]+)', 2) AS host, regexp_replace(url, '[0-9]+', '#') AS shape FROM {pages}", "SELECT page_id, regexp_extract(url, '^(https?)://([^/]+)', 2) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM {pages}")
_add("str_substr", "SELECT doc_id, substring(text, 3, 10) AS piece, left(text, 4) AS l, right(text, 4) AS r, length(text) AS n FROM {documents}", "SELECT doc_id, substring(text, 3, 10) AS piece, left(text, 4) AS l, right(text, 4) AS r, CAST(length(text) AS INTEGER) AS n FROM {documents}")
_add("str_translate", "SELECT n_nationkey, translate(n_name, 'AEIOU', '4310') AS t FROM {nation}")
_add("str_instr", "SELECT n_nationkey, instr(n_name, 'A') AS at, locate('N', n_name) AS at_n FROM {nation}", "SELECT n_nationkey, CAST(instr(n_name, 'A') AS INTEGER) AS at, CAST(instr(n_name, 'N') AS INTEGER) AS at_n FROM {nation}")
_add("str_reverse", "SELECT n_nationkey, reverse(n_name) AS r, repeat(left(n_name, 1), 3) AS x FROM {nation}")
_add("str_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS d FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey", "SELECT a.n_name AS a, b.n_name AS b, CAST(levenshtein(a.n_name, b.n_name) AS INTEGER) AS d FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey")
_add("str_digest", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM {documents}", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM {documents}")
_add("str_concat_ws", "SELECT c_custkey, concat_ws('|', c_name, c_mktsegment) AS s FROM {customer}")
_add("strip_html", "SELECT page_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' '), '[ ]+', ' ')) AS body FROM {pages}", "SELECT page_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ ]+', ' ', 'g')) AS body FROM {pages}")
_add("page_lang", "SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang FROM {pages}")
_add("url_parts", "SELECT page_id, parse_url(url, 'HOST') AS host, parse_url(url, 'PROTOCOL') AS scheme, parse_url(url, 'PATH') AS path FROM {pages}", "SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host, regexp_extract(url, '^([a-z]+)', 1) AS scheme, regexp_extract(url, '://[^/?#]+([^?#]*)', 1) AS path FROM {pages}")

# ---- dates
_add("dt_trunc", "SELECT event_id, unix_micros(date_trunc('HOUR', ts)) AS h, unix_micros(date_trunc('MONTH', ts)) AS m FROM {events}", "SELECT event_id, epoch_us(date_trunc('hour', ts)) AS h, epoch_us(CAST(date_trunc('month', ts) AS TIMESTAMP)) AS m FROM {events}")
_add("dt_extract", "SELECT event_id, hour(ts) AS h, day(ts) AS d, month(ts) AS m, year(ts) AS y, dayofyear(ts) AS doy FROM {events}", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS h, CAST(day(ts) AS INTEGER) AS d, CAST(month(ts) AS INTEGER) AS m, CAST(year(ts) AS INTEGER) AS y, CAST(dayofyear(ts) AS INTEGER) AS doy FROM {events}")
_add("dt_add", "SELECT o_orderkey, unix_micros(o_orderdate + INTERVAL 7 DAY) AS later FROM {orders}", "SELECT o_orderkey, epoch_us(o_orderdate + INTERVAL 7 DAY) AS later FROM {orders}")
_add("dt_diff", "SELECT o_orderkey, datediff(DATE '2000-01-01', CAST(o_orderdate AS DATE)) AS days FROM {orders}", "SELECT o_orderkey, CAST(DATE '2000-01-01' - CAST(o_orderdate AS DATE) AS INTEGER) AS days FROM {orders}")
_add("dt_format", "SELECT o_orderkey, date_format(o_orderdate, 'yyyy-MM-dd') AS d FROM {orders}", "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m-%d') AS d FROM {orders}")
_add("dt_interval", "SELECT l_orderkey, l_linenumber FROM {lineitem} WHERE l_shipdate >= (SELECT min(l_shipdate) FROM {lineitem}) AND l_shipdate < (SELECT min(l_shipdate) FROM {lineitem}) + INTERVAL 3 MONTH")
_add("dt_epoch", "SELECT event_id, unix_micros(ts) AS us, CAST(floor(unix_micros(ts) / 3600000000) AS BIGINT) AS hours FROM {events}", "SELECT event_id, epoch_us(ts) AS us, CAST(floor(epoch_us(ts) / 3600000000) AS BIGINT) AS hours FROM {events}")

# ---- mathematics
_add("math_round", "SELECT l_orderkey, l_linenumber, round(l_extendedprice, 1) AS r, floor(l_extendedprice) AS f, ceil(l_extendedprice) AS c, abs(-l_tax) AS a FROM {lineitem}", "SELECT l_orderkey, l_linenumber, round(l_extendedprice, 1) AS r, CAST(floor(l_extendedprice) AS BIGINT) AS f, CAST(ceil(l_extendedprice) AS BIGINT) AS c, abs(-l_tax) AS a FROM {lineitem}")
_add("math_log_exp", "SELECT l_orderkey, l_linenumber, round(ln(l_quantity + 1), 6) AS l, round(exp(-l_discount), 6) AS e, round(sqrt(l_quantity), 6) AS s FROM {lineitem}")
_add("math_trig", "SELECT event_id, round(sin(value), 6) AS s, round(cos(value), 6) AS c, round(atan2(value, 2), 6) AS a FROM {events}")
_add("math_pow", "SELECT event_id, round(pow(value, 2), 1) AS p, round(cbrt(value), 6) AS c FROM {events}")
_add("math_mod", "SELECT p_partkey, p_partkey % 7 AS m, pmod(-p_partkey, 7) AS pm, p_partkey div 10 AS d FROM {part}", "SELECT p_partkey, p_partkey % 7 AS m, ((-p_partkey % 7) + 7) % 7 AS pm, p_partkey // 10 AS d FROM {part}")
_add("math_bits", "SELECT p_partkey, p_partkey & 12 AS a, p_partkey | 5 AS o, p_partkey ^ 9 AS x, shiftleft(p_partkey, 2) AS l, bit_count(p_partkey) AS n FROM {part}", "SELECT p_partkey, p_partkey & 12 AS a, p_partkey | 5 AS o, xor(p_partkey, 9) AS x, p_partkey << 2 AS l, CAST(bit_count(p_partkey) AS INTEGER) AS n FROM {part}")
_add("math_greatest", "SELECT l_orderkey, l_linenumber, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS s FROM {lineitem}")
_add("math_decimal_sum", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS STRING) AS total FROM {lineitem} GROUP BY l_returnflag", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS VARCHAR) AS total FROM {lineitem} GROUP BY l_returnflag")
_add("sigmoid_scores", "SELECT event_id, round(1 / (1 + exp(-(value - 50) / 10)), 6) AS p FROM {events}")

# ---- arrays, maps, structs, JSON
_add("arr_dot", "SELECT vec_id, round(aggregate(zip_with(embedding, embedding, (x, y) -> CAST(x AS DOUBLE) * y), 0D, (s, x) -> s + x), 5) AS dot FROM {embeddings}", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS dot FROM {embeddings}")
_add("arr_axpy", "SELECT vec_id, round(zip_with(embedding, reverse(embedding), (x, y) -> CAST(x AS DOUBLE) + 0.5D * y)[3], 6) AS v3 FROM {embeddings}", "SELECT vec_id, round(embedding[4]::DOUBLE + 0.5 * embedding[61]::DOUBLE, 6) AS v3 FROM {embeddings}")
_add("arr_filter", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS positive, exists(embedding, x -> x > 0.3) AS large FROM {embeddings}", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS large FROM {embeddings}")
_add("arr_sort", "SELECT vec_id, round(sort_array(embedding)[0], 5) AS least, round(array_max(embedding), 5) AS most FROM {embeddings}", "SELECT vec_id, round(list_sort(embedding)[1], 5) AS least, round(list_max(embedding), 5) AS most FROM {embeddings}")
_add("arr_setops", "SELECT n_nationkey, size(array_intersect(split(n_name, ''), array('A', 'E', 'I'))) AS vowels, size(array_distinct(split(n_name, ''))) AS letters FROM {nation}", "SELECT n_nationkey, CAST(len(list_intersect(string_split(n_name, ''), ['A', 'E', 'I'])) AS INTEGER) AS vowels, CAST(len(list_distinct(string_split(n_name, ''))) AS INTEGER) AS letters FROM {nation}")
_add("arr_slice", "SELECT vec_id, round(aggregate(slice(embedding, 5, 4), 0D, (s, x) -> s + x), 5) AS part FROM {embeddings}", "SELECT vec_id, round(list_sum(list_transform(embedding[5:8], lambda x: x::DOUBLE)), 5) AS part FROM {embeddings}")
_add("arr_flatten", "SELECT n_regionkey, size(flatten(collect_list(split(n_name, '')))) AS letters FROM {nation} GROUP BY n_regionkey", "SELECT n_regionkey, CAST(len(flatten(list(string_split(n_name, '')))) AS INTEGER) AS letters FROM {nation} GROUP BY n_regionkey")
_add("arr_zip", "SELECT n_nationkey, arrays_zip(sequence(1, 3), split(n_name, ''))[1].`1` AS second FROM {nation}", "SELECT n_nationkey, substr(n_name, 2, 1) AS second FROM {nation}")
_add("map_sparse_dot", "SELECT o_custkey, aggregate(map_values(map_zip_with(m, map_from_entries(array(struct('F', 2L), struct('O', 3L))), (k, a, b) -> coalesce(a, 0L) * coalesce(b, 0L))), 0L, (s, x) -> s + x) AS dot FROM (SELECT o_custkey, map_from_entries(collect_list(struct(o_orderstatus, n))) AS m FROM (SELECT o_custkey, o_orderstatus, count(*) AS n FROM {orders} GROUP BY o_custkey, o_orderstatus) GROUP BY o_custkey)", "SELECT o_custkey, CAST(sum(CASE o_orderstatus WHEN 'F' THEN 2 WHEN 'O' THEN 3 ELSE 0 END) AS BIGINT) AS dot FROM {orders} GROUP BY o_custkey")
_add("map_sparse_axpy", "SELECT o_custkey, map_zip_with(m, map('F', 1L), (k, a, b) -> coalesce(a, 0L) - 2 * coalesce(b, 0L))['F'] AS f FROM (SELECT o_custkey, map_from_entries(collect_list(struct(o_orderstatus, n))) AS m FROM (SELECT o_custkey, o_orderstatus, count(*) AS n FROM {orders} GROUP BY o_custkey, o_orderstatus) GROUP BY o_custkey)", "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') - 2 AS f FROM {orders} GROUP BY o_custkey")
_add("map_filter", "SELECT n_nationkey, size(map_filter(map('a', n_nationkey, 'b', n_regionkey), (k, v) -> v > 2)) AS n FROM {nation}", "SELECT n_nationkey, CAST((n_nationkey > 2)::INT + (n_regionkey > 2)::INT AS INTEGER) AS n FROM {nation}")
_add("map_keys", "SELECT n_nationkey, concat_ws(',', array_sort(map_keys(map(n_name, 1, 'x', 2)))) AS k FROM {nation}", "SELECT n_nationkey, CASE WHEN n_name < 'x' THEN n_name || ',x' ELSE 'x,' || n_name END AS k FROM {nation}")
_add("struct_pack", "SELECT n_nationkey, named_struct('a', n_name, 'b', n_regionkey).b AS b FROM {nation}", "SELECT n_nationkey, struct_pack(a := n_name, b := n_regionkey).b AS b FROM {nation}")
_add("json_props", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k, from_json(props, 'k INT').k + 1 AS k1 FROM {events}", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS INTEGER) + 1 AS k1 FROM {events}")
_add("json_build", "SELECT n_nationkey, to_json(named_struct('k', n_nationkey, 'r', n_regionkey)) AS j FROM {nation}", "SELECT n_nationkey, '{{\"k\":' || n_nationkey || ',\"r\":' || n_regionkey || '}}' AS j FROM {nation}")

# ---- subqueries and SQL surface
_add("subq_scalar", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM {orders})")
_add("subq_in", "SELECT c_custkey FROM {customer} WHERE c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 2)")
_add("subq_exists", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F')")
_add("subq_not_exists", "SELECT p_partkey FROM {part} p WHERE NOT EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_partkey = p.p_partkey AND l.l_quantity > 49)")
_add("subq_correlated", "SELECT p_partkey FROM {part} p WHERE p_retailprice > (SELECT avg(q.p_retailprice) FROM {part} q WHERE q.p_brand = p.p_brand)")
_add("cte_chain", "WITH a AS (SELECT l_partkey, sum(CAST(l_quantity AS BIGINT)) AS q FROM {lineitem} GROUP BY l_partkey), b AS (SELECT max(q) AS m FROM a) SELECT l_partkey FROM a JOIN b ON a.q = b.m")
_RECURSIVE = "WITH RECURSIVE m AS (SELECT event_type, round(avg(value), 3) AS goal FROM {events} GROUP BY event_type), t(event_type, goal, n, w) AS (SELECT event_type, goal, 0, CAST(0 AS DOUBLE) FROM m UNION ALL SELECT event_type, goal, n + 1, w - CAST(0.5 AS DOUBLE) * (w - goal) FROM t WHERE n < 10) SELECT event_type, n, round(w, 6) AS w FROM t"
_add("cte_recursive", _RECURSIVE)

# ---- event-time windows (batch twins of the streaming operators)
_add("win_tumbling", "SELECT unix_micros(window.start) AS start, count(*) AS n FROM (SELECT window(ts, '1 hour') AS window FROM {events}) GROUP BY window.start", "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, count(*) AS n FROM {events} GROUP BY 1")
_add("win_sliding", "SELECT unix_micros(w.start) AS start, count(*) AS n FROM (SELECT window(ts, '2 hours', '1 hour') AS w FROM {events}) GROUP BY w.start", "SELECT start - h * 3600000000 AS start, count(*) AS n FROM (SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start FROM {events}), range(2) r(h) GROUP BY 1")
_add(
    "win_session",
    "SELECT user_id, unix_micros(w.start) AS start, n FROM (SELECT user_id, session_window(ts, '6 hours') AS w, count(*) AS n FROM {events} GROUP BY user_id, session_window(ts, '6 hours'))",
    """SELECT user_id, min(t) AS start, count(*) AS n FROM (
         SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
           SELECT user_id, event_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM {events}))
       GROUP BY user_id, s""",
)


def run(text: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    used = set(re.findall(r"\{(\w+)\}", text)) & set(TABLES)
    return spark.sql(text, **{t: load(spark, sf_dir, t) for t in used})


def _query(text: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: run(text, spark, sf_dir)


QUERIES = {name: _query(spark) for name, (spark, _) in SQL.items()}
ORACLES = {name: (spark if other is None else other).format(**{t: t for t in TABLES}) for name, (spark, other) in SQL.items()}
