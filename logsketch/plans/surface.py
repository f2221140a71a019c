"""Operators around the methods, phrased as questions to the log and the tables; each text runs on both engines."""

from __future__ import annotations

from .dialect import Text

DUCK_DAYS = "datediff('day', cast(o_orderdate AS date), cast(l_shipdate AS date))"
SHARED: dict[str, Text] = {
    # scans, projections, filters
    "op_scan_prune": lambda x: "SELECT event_type, count(*) AS n FROM events WHERE ts >= timestamp '2024-01-05 00:00:00' AND ts < timestamp '2024-01-06 00:00:00' GROUP BY event_type",
    "op_project_exprs": lambda x: "SELECT stmt_id, length(sql) AS len, upper(substr(sql, 1, 6)) AS head, hour(ts) AS hour_of_day FROM log",
    "op_filter_predicates": lambda x: "SELECT stmt_id FROM log WHERE klass IN ('SELECT', 'UNION') AND user_id BETWEEN 10 AND 400 AND sql LIKE '%orders%' AND NOT sql LIKE '%LIMIT%' AND (fam IS NOT DISTINCT FROM 1 OR fam > 3)",
    "op_sample_biased": lambda x: "SELECT fam, count(*) AS n FROM log WHERE stmt_id * 7919 % 100 < CASE WHEN fam < 15 THEN 30 ELSE 5 END GROUP BY fam",
    # joins
    "op_join_inner": lambda x: "SELECT c.c_mktsegment, count(*) AS n FROM log l JOIN customer c ON l.user_id = c.c_custkey GROUP BY c.c_mktsegment",
    "op_join_left": lambda x: "SELECT l.klass, sum(CASE WHEN c.c_custkey IS NULL THEN 1 ELSE 0 END)::bigint AS missing, count(*) AS n FROM log l LEFT JOIN customer c ON l.user_id = c.c_custkey GROUP BY l.klass",
    "op_join_right": lambda x: "SELECT c.c_nationkey, count(l.stmt_id) AS n FROM log l RIGHT JOIN customer c ON l.user_id = c.c_custkey GROUP BY c.c_nationkey",
    "op_join_full": lambda x: "SELECT a.k AS left_key, b.k AS right_key, a.n AS left_n, b.n AS right_n FROM (SELECT user_id AS k, count(*) AS n FROM log WHERE klass = 'SELECT' GROUP BY user_id) a FULL OUTER JOIN (SELECT user_id AS k, count(*) AS n FROM log WHERE klass = 'DELETE' GROUP BY user_id) b ON a.k = b.k",
    "op_join_broadcast": lambda x: "SELECT /*+ BROADCAST(n) */ n.n_name, count(*) AS n_customers FROM customer c JOIN nation n ON c.c_nationkey = n.n_nationkey GROUP BY n.n_name",
    "op_join_sortmerge": lambda x: "SELECT /*+ MERGE(o) */ o.o_orderstatus, count(*) AS n FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderstatus",
    "op_join_shuffle_hash": lambda x: "SELECT /*+ SHUFFLE_HASH(o) */ o.o_orderpriority, count(*) AS n FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderpriority",
    "op_join_semi": lambda x: "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R') GROUP BY o_orderstatus",
    "op_join_anti": lambda x: "SELECT o_orderstatus, count(*) AS n FROM orders o WHERE NOT EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_returnflag = 'R') GROUP BY o_orderstatus",
    "op_join_null_aware_anti": lambda x: "SELECT (SELECT count(*) FROM nation WHERE n_regionkey NOT IN (SELECT k FROM (VALUES (1), (CAST(NULL AS int))) t(k))) AS with_null, (SELECT count(*) FROM nation WHERE n_regionkey NOT IN (SELECT k FROM (VALUES (1), (2)) t(k))) AS without_null",
    "op_join_theta": lambda x: x.pick(
        # Balances less than 50 apart lie in the same or in neighbouring bands of 64, by which both engines divide exactly.
        "WITH c AS (SELECT c_nationkey, c_custkey, c_acctbal, floor(least(greatest(c_acctbal / 64, -1e18D), 1e18D)) AS band FROM customer WHERE c_acctbal IS NOT NULL) SELECT /*+ SHUFFLE_HASH(a) */ a.c_nationkey, count(*) AS n FROM c a JOIN (SELECT c_nationkey, c_custkey, c_acctbal, explode(array(band - 1, band, band + 1)) AS band FROM c) b ON a.c_nationkey = b.c_nationkey AND a.band = b.band AND a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) < 50 GROUP BY a.c_nationkey",
        "SELECT a.c_nationkey, count(*) AS n FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) < 50 GROUP BY a.c_nationkey",
    ),
    "op_join_range": lambda x: f"SELECT b.lo AS bucket, count(*) AS n FROM (SELECT {x.epoch('ts')} AS t FROM events) e JOIN (SELECT DISTINCT cast(floor({x.epoch('ts')} / 21600) AS bigint) AS lo FROM events) b ON cast(floor(e.t / 21600) AS bigint) = b.lo AND e.t >= b.lo * 21600 AND e.t < (b.lo + 1) * 21600 GROUP BY b.lo",
    "op_join_interval": lambda x: f"SELECT s.user_id, count(*) AS n FROM events s JOIN events e ON s.user_id = e.user_id AND s.event_type = 'signup' AND e.event_type = 'error' AND {x.epoch('e.ts')} > {x.epoch('s.ts')} AND {x.epoch('e.ts')} <= {x.epoch('s.ts')} + 3600 GROUP BY s.user_id",
    "op_join_asof": lambda x: f"WITH u AS (SELECT event_id, user_id, {x.epoch('ts')} AS t, event_type, CASE WHEN event_type = 'purchase' THEN {x.epoch('ts')} END AS p FROM events WHERE event_type IN ('purchase', 'error')) SELECT event_id, last_purchase FROM (SELECT event_id, event_type, max(p) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM u) z WHERE event_type = 'error'",
    "op_join_cross": lambda x: "SELECT r.r_name, k.klass, coalesce(n.n, 0) AS n FROM region r CROSS JOIN (SELECT DISTINCT klass FROM log) k LEFT JOIN (SELECT rr.r_name, l.klass, count(*) AS n FROM log l JOIN customer c ON l.user_id = c.c_custkey JOIN nation nn ON c.c_nationkey = nn.n_nationkey JOIN region rr ON nn.n_regionkey = rr.r_regionkey GROUP BY rr.r_name, l.klass) n ON n.r_name = r.r_name AND n.klass = k.klass",
    "op_join_self_tree": lambda x: "SELECT concat(r_name, '/', n_name, '/', c_mktsegment) AS path, count(*) AS n FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON n_nationkey = c_nationkey GROUP BY r_name, n_name, c_mktsegment",
    "op_lateral_explode": lambda x: f"SELECT token, count(*) AS n FROM (SELECT {x.pick('explode(' + x.words('sql') + ')', 'unnest(' + x.words('sql') + ')')} AS token FROM log WHERE klass = 'DELETE') t GROUP BY token",
    "op_lateral_subquery": lambda x: "SELECT o_orderkey, l_linenumber, l_extendedprice FROM (SELECT o_orderkey, l_linenumber, l_extendedprice, row_number() OVER (PARTITION BY o_orderkey ORDER BY l_extendedprice DESC, l_linenumber) AS r FROM orders JOIN lineitem ON o_orderkey = l_orderkey) t WHERE r = 1",
    # aggregation
    "op_agg_hash": lambda x: "SELECT klass, user_id % 10 AS bucket, count(*) AS n, sum(length(sql))::bigint AS chars FROM log GROUP BY klass, user_id % 10",
    "op_agg_partial_final": lambda x: "SELECT user_id, count(*) AS n, min(stmt_id) AS first_stmt, max(stmt_id) AS last_stmt FROM log GROUP BY user_id",
    "op_agg_sort": lambda x: f"SELECT klass, fam, {x.items('stmt_id')} AS ids FROM log WHERE klass IN ('UNION', 'DELETE') GROUP BY klass, fam",
    "op_agg_distinct": lambda x: f"SELECT klass, count(DISTINCT user_id) AS users, count(DISTINCT {x.fp('sql')}) AS structures FROM log GROUP BY klass",
    "op_agg_approx_distinct": lambda x: f"SELECT klass, {x.pick('abs(approx_count_distinct(user_id, 0.02) - count(DISTINCT user_id)) <= 0.1 * count(DISTINCT user_id)', 'true')} AS close_enough FROM log GROUP BY klass",
    "op_agg_percentiles": lambda x: f"SELECT event_type, round({x.pick('percentile(value, 0.9)', 'quantile_cont(value, 0.9)')}, 6) AS p90, round(median(value), 6) AS p50 FROM events GROUP BY event_type",
    "op_agg_argmax": lambda x: f"SELECT klass, {x.pick('max_by(hour_of_day, n * 100 - hour_of_day)', 'arg_max(hour_of_day, n * 100 - hour_of_day)')} AS busiest FROM (SELECT klass, hour(ts) AS hour_of_day, count(*) AS n FROM log GROUP BY klass, hour(ts)) t GROUP BY klass",
    "op_agg_stats": lambda x: "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_discount), 6) AS cov FROM lineitem GROUP BY l_returnflag",
    "op_agg_bool": lambda x: "SELECT user_id, bool_and(value > 1) AS every, bool_or(value > 200) AS some FROM events GROUP BY user_id",
    "op_agg_filter": lambda x: "SELECT user_id, count(*) FILTER (WHERE event_type = 'error') AS errors, round(sum(value) FILTER (WHERE event_type = 'purchase'), 4) AS spent FROM events GROUP BY user_id",
    "op_agg_collect": lambda x: f"SELECT user_id, {x.items('event_type')} AS every, {x.items('event_type', True)} AS kinds FROM events GROUP BY user_id",
    "op_rollup": lambda x: "SELECT klass, cast(date_trunc('day', ts) AS date) AS day, count(*) AS n FROM log GROUP BY ROLLUP (klass, cast(date_trunc('day', ts) AS date))",
    "op_cube": lambda x: "SELECT klass, fam % 5 AS f, count(*) AS n, grouping(klass) AS g FROM log GROUP BY CUBE (klass, fam % 5)".replace("grouping(klass)", "cast(grouping(klass) AS bigint)"),
    "op_grouping_sets": lambda x: "SELECT klass, fam, count(*) AS n FROM log GROUP BY GROUPING SETS ((klass), (fam), ())",
    "op_pivot": lambda x: "SELECT user_id, " + ", ".join(f"count(CASE WHEN event_type = '{e}' THEN 1 END) AS {e}" for e in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY user_id",
    "op_having": lambda x: "SELECT user_id, count(*) AS n FROM log GROUP BY user_id HAVING count(*) > 12",
    # windows
    "op_win_rank": lambda x: "SELECT user_id, n, row_number() OVER (ORDER BY n DESC, user_id) AS rn, rank() OVER (ORDER BY n DESC) AS rk, dense_rank() OVER (ORDER BY n DESC) AS dr, round(percent_rank() OVER (ORDER BY n), 6) AS pr, round(cume_dist() OVER (ORDER BY n), 6) AS cd FROM (SELECT user_id, count(*) AS n FROM log GROUP BY user_id) t",
    "op_win_offset": lambda x: f"SELECT event_id, t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) AS gap, lead(event_id) OVER (PARTITION BY user_id ORDER BY t, event_id) AS next_event FROM (SELECT event_id, user_id, {x.epoch('ts')} AS t FROM events) e",
    "op_win_value": lambda x: "SELECT event_id, first_value(event_id) OVER w AS first_event, last_value(event_id) OVER w AS last_event, nth_value(event_id, 2) OVER w AS second_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "op_win_rows": lambda x: "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM events",
    "op_win_range": lambda x: f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT event_id, user_id, {x.epoch('ts')} AS t FROM events) e",
    "op_win_first_seen": lambda x: f"WITH f AS (SELECT {x.fp('sql')} AS fp, min(stmt_id) AS first_id FROM log WHERE klass = 'SELECT' GROUP BY 1) SELECT first_id, row_number() OVER (ORDER BY first_id) AS structures FROM f",
    "op_sessionize": lambda x: f"WITH e AS (SELECT event_id, user_id, {x.epoch('ts')} AS t FROM events), g AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) <= 1800 THEN 0 ELSE 1 END AS starts FROM e), s AS (SELECT user_id, sum(starts) OVER (PARTITION BY user_id ORDER BY t, event_id) AS session FROM g) SELECT user_id, cast(max(session) AS bigint) AS sessions FROM s GROUP BY user_id",
    # order, limit, sets
    "op_sort": lambda x: "SELECT stmt_id, user_id FROM log WHERE klass = 'DELETE' ORDER BY user_id DESC, stmt_id",
    "op_limit_offset": lambda x: "SELECT stmt_id, klass FROM log ORDER BY stmt_id LIMIT 20 OFFSET 35",
    "op_topk": lambda x: f"SELECT {x.fp('sql')} AS fp, count(*) AS n FROM log GROUP BY 1 ORDER BY n DESC, fp LIMIT 10",
    "op_topk_group": lambda x: f"SELECT klass, fp, n FROM (SELECT klass, fp, n, row_number() OVER (PARTITION BY klass ORDER BY n DESC, fp) AS r FROM (SELECT klass, {x.fp('sql')} AS fp, count(*) AS n FROM log GROUP BY 1, 2) a) b WHERE r <= 3",
    **{
        f"op_{name}": (lambda x, op=op: f"SELECT {x.fp('sql')} AS fp FROM log WHERE stmt_id % 2 = 0 AND klass IN ('SELECT', 'UPDATE') {op} SELECT {x.fp('sql')} AS fp FROM log WHERE stmt_id % 2 = 1 AND klass IN ('SELECT', 'INSERT')")
        for name, op in (("union", "UNION ALL"), ("union_distinct", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL"))
    },
    # functions
    "op_str_regex": lambda x: "SELECT stmt_id, regexp_extract(sql, 'FROM ([a-z]+)', 1) AS source FROM log WHERE klass = 'SELECT'",
    "op_str_basic": lambda x: "SELECT stmt_id, upper(substr(sql, 1, 10)) AS up, lower(trim(sql)) AS low, replace(sql, ' ', '_') AS snake, lpad(cast(user_id AS string), 6, '0') AS padded FROM log WHERE klass = 'UPDATE'",
    "op_str_split": lambda x: f"SELECT stmt_id, {x.n(x.words('sql'))} AS n_words FROM log",
    "op_str_hash": lambda x: f"SELECT stmt_id, md5(sql) AS m, {x.sha('sql')} AS s FROM log",
    "op_str_distance": lambda x: "SELECT stmt_id, cast(levenshtein(substr(sql, 1, 30), 'SELECT o_orderkey FROM orders') AS bigint) AS d FROM log WHERE klass IN ('UNION', 'DELETE')",
    "op_date_parts": lambda x: f"SELECT event_id, year(ts) AS y, month(ts) AS m, day(ts) AS d, hour(ts) AS h, {x.pick('dayofweek(ts) - 1', 'dayofweek(ts)')} AS w FROM events",
    "op_date_arith": lambda x: f"SELECT o_orderkey, {x.pick('datediff(l_shipdate, o_orderdate)', DUCK_DAYS)} AS days FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_linenumber = 1",
    "op_date_trunc": lambda x: "SELECT date_trunc('hour', ts) AS h, count(*) AS n FROM events GROUP BY date_trunc('hour', ts)",
    "op_math": lambda x: "SELECT event_id, round(ln(value + 1), 6) AS l, round(sqrt(value), 6) AS s, round(power(value, 1.5), 4) AS p, cast(floor(value) AS bigint) AS f, cast(ceil(value) AS bigint) AS c, round(abs(value - 50), 4) AS a, event_id % 7 AS m, greatest(value, 10.0) AS g FROM events",
    "op_arr_hof": lambda x: f"SELECT l_orderkey, {x.pick('aggregate(transform(filter(q, v -> v > 10), v -> v * 2), 0.0D, (a, b) -> a + b)', 'coalesce(list_sum(list_transform(list_filter(q, lambda v: v > 10), lambda v: v * 2)), 0.0)')} AS total FROM (SELECT l_orderkey, {x.pick('collect_list(l_quantity)', 'list(l_quantity)')} AS q FROM lineitem GROUP BY l_orderkey) t",
    "op_arr_sets": lambda x: f"SELECT l_orderkey, {x.pick('size(array_intersect(a, array(1, 2, 3)))', 'cast(len(list_intersect(a, [1, 2, 3])) AS int)')} AS both FROM (SELECT l_orderkey, {x.pick('collect_set(l_linenumber)', 'list(DISTINCT l_linenumber)')} AS a FROM lineitem GROUP BY l_orderkey) t",
    "op_arr_slice": lambda x: f"SELECT l_orderkey, {x.pick('array_join(slice(array_sort(collect_list(l_linenumber)), 1, 2), ' + repr('|') + ')', 'array_to_string(list_sort(list(l_linenumber))[1:2], ' + repr('|') + ')')} AS head FROM lineitem GROUP BY l_orderkey",
    "op_arr_agg": lambda x: f"SELECT l_orderkey, {x.pick('array_max(collect_list(l_tax))', 'list_max(list(l_tax))')} AS top FROM lineitem GROUP BY l_orderkey",
    "op_map_funcs": lambda x: f"SELECT o, {x.pick('map_from_entries(collect_list(struct(b, n)))[' + repr('Brand#11') + ']', 'map_from_entries(list((b, n)))[' + repr('Brand#11') + ']')} AS brand_11 FROM (SELECT l_orderkey AS o, p_brand AS b, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2) t GROUP BY o",
    "op_struct_funcs": lambda x: f"SELECT event_id, s.a AS a, s.b AS b FROM (SELECT event_id, {x.pick('named_struct(' + repr('a') + ', user_id, ' + repr('b') + ', event_type)', '{' + repr('a') + ': user_id, ' + repr('b') + ': event_type}')} AS s FROM events) t",
    "op_json_path": lambda x: f"SELECT event_id, cast({x.pick('get_json_object', 'json_extract_string')}(props, '$.k') AS bigint) AS k FROM events",
    "op_json_parse": lambda x: f"SELECT event_id, {x.pick('from_json(props, ' + repr('k bigint') + ').k', 'cast(json_extract(props, ' + repr('$.k') + ') AS bigint)')} AS k FROM events",
    "op_json_write": lambda x: f"SELECT event_id, {x.pick('to_json(named_struct(' + repr('u') + ', user_id))', 'cast(json_object(' + repr('u') + ', user_id) AS string)')} AS j FROM events",
    "op_variant": lambda x: f"SELECT event_id, {x.pick('variant_get(parse_json(props), ' + repr('$.k') + ', ' + repr('bigint') + ')', 'cast(json_extract(props, ' + repr('$.k') + ') AS bigint)')} AS k FROM events",
    "op_decimal_money": lambda x: "SELECT l_returnflag, cast(sum(cast(l_extendedprice AS decimal(12, 2))) AS decimal(22, 2)) AS total FROM lineitem GROUP BY l_returnflag",
    "op_cast_try": lambda x: "SELECT conv_id, turn, try_cast(substr(text, 1, 3) AS bigint) AS number_at_start FROM conversations",
    # SQL surface
    "op_cte": lambda x: "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), top AS (SELECT max(n) AS m FROM big) SELECT o_custkey, n FROM big, top WHERE n = m",
    "op_cte_recursive": lambda x: "WITH RECURSIVE t(name, path, level) AS (SELECT r_name, r_name, 0 FROM region UNION ALL SELECT n_name, concat(t.path, '/', n_name), 1 FROM nation JOIN region ON n_regionkey = r_regionkey JOIN t ON t.name = r_name AND t.level = 0) SELECT name, path, level FROM t",
    "op_subq_scalar": lambda x: "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)",
    "op_subq_exists": lambda x: "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'O')",
    "op_subq_in": lambda x: "SELECT n_name FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9000)",
}
