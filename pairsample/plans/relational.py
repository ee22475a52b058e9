"""Relational operators that users put before and after the methods, as registered queries with their checks."""

from __future__ import annotations

from pyspark.sql import functions as F

from pairsample.plans.queries import MU, SEED, W4, W5, sql_exact, sql_pairs, sql_report, sql_sample
from pairsample.plans.registry import register
from pairsample.sources import workloads
from pairsample.sources.tables import run_sql
from pairsample.sources.workloads import duck, duck_view
from pairsample.streaming import streams


def both(key: str, spark_sql: str, duck_sql: str | None = None) -> None:
    """A query whose text both engines read, or two spellings of it."""
    register(key, lambda s, d: run_sql(s, d, spark_sql), duck(duck_sql or spark_sql))


B4, D4 = workloads.sql(W4), duck_view(W4)
SUP = "SELECT l_partkey AS i, count(*) AS c FROM {lineitem} GROUP BY l_partkey"
both("op_project", "SELECT l_orderkey AS t, l_partkey AS i FROM {lineitem}")
both("scan_parquet", "SELECT o_orderkey, o_custkey FROM {orders}")
both("op_case", f"SELECT i, CASE WHEN c < 25 THEN 'rare' WHEN c < 35 THEN 'mid' ELSE 'frequent' END AS class, coalesce(nullif(c, 30), -1) AS c FROM ({SUP}) s")
both("op_filter", "SELECT l_orderkey, l_partkey FROM {lineitem} WHERE l_returnflag IN ('A', 'R') AND l_quantity BETWEEN 10 AND 20 AND l_shipdate IS NOT NULL AND l_linestatus LIKE 'F%'")
both("op_filter_dates", "SELECT DISTINCT o_custkey AS t, l_partkey AS i FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey WHERE year(o_orderdate) = 1995")
for _key, _hint in (("op_join_broadcast", "BROADCAST(s)"), ("op_join_merge", "MERGE(s)"), ("op_join_shuffle_hash", "SHUFFLE_HASH(s)")):
    both(_key, f"SELECT /*+ {_hint} */ b.l_orderkey AS t, b.l_partkey AS i, s.c FROM {{lineitem}} b JOIN ({SUP}) s ON b.l_partkey = s.i", f"SELECT b.l_orderkey AS t, b.l_partkey AS i, s.c FROM {{lineitem}} b JOIN ({SUP}) s ON b.l_partkey = s.i")
_range = "WITH b AS ({b}), s AS (SELECT i, count(*) AS c FROM b GROUP BY i), e AS (SELECT b.t, b.i, s.c FROM b JOIN s ON b.i = s.i) SELECT x.i, count(*) AS partners FROM e x JOIN e y ON x.t = y.t AND y.c > x.c AND y.c < x.c + 20 GROUP BY x.i"
both("op_range_join", _range.replace("{b}", B4), _range.replace("{b}", D4))
_exact5 = f"WITH {sql_exact(W5, 'cosine', 0.3)}"


def _tp(s, d):
    from pairsample.operators.baselines import exact_pairs

    return exact_pairs(workloads.baskets(s, d, W5), "cosine", 0.3)


def _rp(s, d):
    from pairsample.operators import reporting, sampling

    return reporting.report(sampling.sample_pairs(workloads.baskets(s, d, W5), "cosine", MU, 0.3, SEED), "cosine", MU, 0.3)


_apx = "ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5), tp AS (SELECT i, j FROM ap WHERE CAST(k AS DOUBLE) / sqrt(CAST(ci AS DOUBLE) * CAST(cj AS DOUBLE)) >= 0.299999999999e0)"
_rpx = f"WITH {sql_sample(W5, 'cosine', MU, 0.3)}, rp AS ({sql_report('cosine', MU, 0.3)}), {_apx}"
register("op_anti_missed", lambda s, d: _tp(s, d).select("i", "j").join(_rp(s, d).select("i", "j"), ["i", "j"], "left_anti"), f"{_rpx} SELECT i, j FROM tp WHERE (i, j) NOT IN (SELECT (i, j) FROM rp)")


def _exact(s, d, view, measure, delta):
    from pairsample.operators.baselines import exact_pairs

    return exact_pairs(workloads.baskets(s, d, view), measure, delta)


def _sql_pairs_by(measure, delta):
    return f"WITH {sql_exact(W5, measure, delta)} SELECT i, j FROM tp"


def _all(s, d, view):
    from pairsample.operators.baselines import all_pairs

    return all_pairs(workloads.baskets(s, d, view))


def _sup(s, d):
    from pairsample.operators.baskets import support_counts

    return support_counts(workloads.baskets(s, d, W5))


def _udtf(s, d):
    """The sample drawn by the table function, one lateral call for each packed transaction."""
    from pairsample.functions.sql_functions import register_pairs_of
    from pairsample.operators import sampling

    register_pairs_of(s, "cosine", "pairs_of_transaction")
    packed = sampling.pack(sampling.sample_rows(workloads.baskets(s, d, W4), "cosine", SEED))
    text = "SELECT least(p.i, p.j) AS i, greatest(p.i, p.j) AS j, count(*) AS k FROM {b} b, LATERAL pairs_of_transaction(transform(b.a, x -> CAST(x.i AS STRING)), transform(b.a, x -> x.c), b.r, 0.5D, 15D, 1D) p GROUP BY 1, 2"
    return s.sql(text, b=packed)


def query(key: str, over, sql: str) -> None:
    """A step over the exact pairs tp."""
    register(key, lambda s, d: over(_tp(s, d), s, d), f"{_exact5} {sql}")


query(
    "op_left_partner",
    lambda p, s, d: _sup(s, d).select("i").join(p.groupBy("i").agg(F.max("sim").alias("best")), "i", "left"),
    "SELECT s.i, z.best FROM s LEFT JOIN (SELECT i, max(sim) AS best FROM tp GROUP BY i) z ON s.i = z.i",
)
query("op_best_partner", lambda p, s, d: p.groupBy("i").agg(F.max_by("j", F.struct("sim", "j")).alias("j"), F.max("sim").alias("sim")), "SELECT i, j, sim FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY sim DESC, j DESC) AS q FROM tp) z WHERE q = 1")
query("op_filtered_agg", lambda p, s, d: p.agg(F.count_if(F.col("sim") >= 0.32).alias("high"), F.sum(F.when(F.col("k") > 100, 1).otherwise(0)).alias("often")), "SELECT count(*) FILTER (sim >= 0.32) AS high, sum(CASE WHEN k > 100 THEN 1 ELSE 0 END)::BIGINT AS often FROM tp")
_over = "SELECT i, j, CAST(rank() OVER w AS INT) AS r, CAST(dense_rank() OVER w AS INT) AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, CAST(ntile(4) OVER (PARTITION BY i ORDER BY sim DESC, j) AS INT) AS nt FROM {p} WINDOW w AS (PARTITION BY i ORDER BY sim DESC)"
query("op_rank_pairs", lambda p, s, d: s.sql(_over, p=p), _over.replace("{p}", "tp"))
_run = "SELECT i, j, sum(1) OVER (PARTITION BY i ORDER BY sim DESC, j ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS outputs FROM {p}"
query("op_running_outputs", lambda p, s, d: s.sql(_run, p=p), _run.replace("{p}", "tp").replace("sum(1)", "CAST(sum(1)").replace("CURRENT ROW)", "CURRENT ROW) AS BIGINT)"))
_frame = "SELECT i, c, CAST(count(*) OVER (ORDER BY c RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS BIGINT) AS near FROM ({s}) q"
both("op_range_frame", "SELECT i, c, CAST(count(*) OVER (PARTITION BY c DIV 1000 ORDER BY c RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS BIGINT) AS near FROM (" + SUP + ") q", "SELECT i, c, CAST(count(*) OVER (PARTITION BY c // 1000 ORDER BY c RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS BIGINT) AS near FROM (" + SUP + ") q")
_nth = "SELECT i, first_value(j) OVER w AS a, nth_value(j, 2) OVER w AS b, last_value(j) OVER w AS z FROM {p} WINDOW w AS (PARTITION BY i ORDER BY sim DESC, j ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
query("op_nth_value", lambda p, s, d: s.sql(_nth, p=p), _nth.replace("{p}", "tp"))
query("op_topk_pairs", lambda p, s, d: p.orderBy(F.col("sim").desc(), "i", "j").limit(100), "SELECT i, j, k, ci, cj, sim FROM tp ORDER BY sim DESC, i, j LIMIT 100")
_top3 = "SELECT i, j, sim FROM (SELECT i, j, sim, row_number() OVER (PARTITION BY i ORDER BY sim DESC, j) AS q FROM {p}) z WHERE q <= 3"
query("op_topk_per_item", lambda p, s, d: s.sql(_top3, p=p), _top3.replace("{p}", "tp"))
query("op_limit_offset", lambda p, s, d: p.orderBy("i", "j").offset(20).limit(20).select("i", "j"), "SELECT i, j FROM tp ORDER BY i, j LIMIT 20 OFFSET 20")
query("op_scalar_subquery", lambda p, s, d: s.sql("SELECT i, j FROM {p} WHERE sim > (SELECT avg(sim) FROM {p}) + 1e-7", p=p), "SELECT i, j FROM tp WHERE sim > (SELECT avg(sim) FROM tp) + 1e-7")
_asof = """SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, max(o2.o_orderdate) AS latest FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey
JOIN {orders} o2 ON o2.o_custkey = o.o_custkey AND o2.o_orderdate <= l.l_shipdate GROUP BY 1, 2, 3, 4, 5"""
both("op_asof", _asof)
both("op_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts BETWEEN a.ts - INTERVAL '1' HOUR AND a.ts + INTERVAL '1' HOUR")
_named = "SELECT p.i, p.j, a.n_name AS first, b.n_name AS second, p.sim FROM {p} p JOIN {supplier} x ON p.i = x.s_suppkey JOIN {nation} a ON x.s_nationkey = a.n_nationkey JOIN {supplier} y ON p.j = y.s_suppkey JOIN {nation} b ON y.s_nationkey = b.n_nationkey"
register(
    "op_enrich_names",
    lambda s, d: run_sql(s, d, _named, p=_exact(s, d, W4, "cosine", 0.3)),
    f"WITH {sql_exact(W4, 'cosine', 0.3)} " + duck(_named.replace("{p}", "tp")),
)
_geo = "{orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey JOIN {nation} n ON c.c_nationkey = n.n_nationkey JOIN {region} r ON n.n_regionkey = r.r_regionkey"
both("op_rollup", f"SELECT r_name, n_nationkey, count(*) AS baskets FROM {_geo} GROUP BY ROLLUP(r_name, n_nationkey)")
both(
    "op_cube",
    f"SELECT r_name, c_mktsegment, p_brand, count(*) AS baskets FROM {_geo} JOIN {{lineitem}} l ON l.l_orderkey = o.o_orderkey JOIN {{part}} p ON p.p_partkey = l.l_partkey GROUP BY CUBE(r_name, c_mktsegment, p_brand)",
)
both("op_grouping_sets", f"SELECT r_name, c_mktsegment, CAST(grouping(r_name) AS INT) AS g, count(*) AS baskets FROM {_geo} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
both("op_quantiles", f"SELECT percentile(b, 0.5D) AS median, percentile(b, 0.9D) AS p90 FROM (SELECT t, count(*) AS b FROM ({B4}) v GROUP BY t) z", f"SELECT quantile_cont(b, 0.5)::DOUBLE AS median, quantile_cont(b, 0.9)::DOUBLE AS p90 FROM (SELECT t, count(*) AS b FROM ({D4}) v GROUP BY t) z")
_mom = "SELECT round(stddev(b), 6) AS sd, round(variance(b), 6) AS var, round(avg(b), 6) AS mean, round(corr(b, t), 6) AS co FROM (SELECT CAST(t AS DOUBLE) AS t, CAST(count(*) AS DOUBLE) AS b FROM ({v}) v GROUP BY t) z"
both("op_moments", _mom.replace("{v}", B4), _mom.replace("{v}", D4))
#: Brands that stand as columns.
BRANDS = ("Brand#1", "Brand#11", "Brand#2", "Brand#25")
register(
    "op_pivot",
    lambda s, d: _all(s, d, "customer_brand").groupBy("i").pivot("j", list(BRANDS)).agg(F.sum("k")).na.fill(0),
    f"WITH {sql_pairs('customer_brand')} SELECT i, " + ", ".join(f"coalesce(sum(k) FILTER (j = '{b}'), 0)::BIGINT AS \"{b}\"" for b in BRANDS) + " FROM ap GROUP BY i",
)
_union = "SELECT concat('o', CAST(l_orderkey AS {s})) AS t, l_partkey AS i FROM {lineitem} UNION ALL SELECT concat('s', CAST(l_suppkey AS {s})), l_partkey FROM {lineitem}"
both("op_union", _union.replace("{s}", "STRING"), _union.replace("{s}", "VARCHAR"))
register(
    "op_intersect_measures",
    lambda s, d: _exact(s, d, W5, "cosine", 0.3).select("i", "j").intersect(_exact(s, d, W5, "jaccard", 0.18).select("i", "j")),
    f"SELECT i, j FROM ({_sql_pairs_by('cosine', 0.3)}) x INTERSECT SELECT i, j FROM ({_sql_pairs_by('jaccard', 0.18)}) y",
)
register(
    "op_except_measures",
    lambda s, d: _exact(s, d, W5, "cosine", 0.3).select("i", "j").exceptAll(_exact(s, d, W5, "lift", 1.02).select("i", "j")),
    f"SELECT i, j FROM ({_sql_pairs_by('cosine', 0.3)}) x EXCEPT ALL SELECT i, j FROM ({_sql_pairs_by('lift', 1.02)}) y",
)
both("op_distinct_basket", "SELECT DISTINCT l_orderkey AS t, l_partkey AS i FROM {lineitem} WHERE l_orderkey IS NOT NULL AND l_partkey IS NOT NULL")
_in_pair = "SELECT s.i, s.c FROM {s} s WHERE EXISTS (SELECT 1 FROM {p} p WHERE p.i = s.i) OR EXISTS (SELECT 1 FROM {p} p WHERE p.j = s.i)"
query("op_exists", lambda p, s, d: s.sql(_in_pair, p=p, s=_sup(s, d)), _in_pair.replace("{p}", "tp").replace("{s}", "s"))
register("op_sql_cte", lambda s, d: run_sql(s, d, f"WITH b AS ({B4}), s AS (SELECT i, count(*) AS c FROM b GROUP BY i), e AS (SELECT b.t, b.i, s.c FROM b JOIN s ON b.i = s.i) SELECT x.i AS i, y.i AS j, count(*) AS k FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY x.i, y.i"), f"WITH {sql_pairs(W4)} SELECT i, j, k FROM ap")
both("op_tokens", "SELECT doc_id, md5(lower(trim(text))) AS h, length(text) AS n, substring(text, 1, 5) AS head FROM {documents}")
both("op_url_paths", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)/', 1) AS host, regexp_replace(url, '[?#].*$', '') AS path FROM {pages}")
both("op_dates", "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, count(*) AS n, min(datediff(o_orderdate, DATE '1990-01-01')) AS d FROM {orders} GROUP BY 1, 2", "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, count(*) AS n, min(date_diff('day', DATE '1990-01-01', o_orderdate::DATE))::INT AS d FROM {orders} GROUP BY 1, 2")
both("op_arrays", "SELECT t, size(a) AS n, element_at(a, 1) AS lo, element_at(a, -1) AS hi, aggregate(a, 0L, (x, y) -> x + y) AS total, size(filter(a, x -> x % 2 = 0)) AS even FROM (SELECT l_orderkey AS t, array_sort(collect_list(l_partkey)) AS a FROM {lineitem} GROUP BY l_orderkey) q", "SELECT l_orderkey AS t, count(*)::INT AS n, min(l_partkey) AS lo, max(l_partkey) AS hi, sum(l_partkey)::BIGINT AS total, count(*) FILTER (l_partkey % 2 = 0)::INT AS even FROM {lineitem} GROUP BY 1")
both("op_array_intersect", "SELECT a.i, b.i AS j, size(array_intersect(a.s, b.s)) AS k, size(array_union(a.s, b.s)) AS u FROM (SELECT l_suppkey AS i, collect_set(l_orderkey) AS s FROM {lineitem} GROUP BY l_suppkey) a JOIN (SELECT l_suppkey AS i, collect_set(l_orderkey) AS s FROM {lineitem} GROUP BY l_suppkey) b ON b.i = a.i + 1", "WITH q AS (SELECT DISTINCT l_suppkey AS i, l_orderkey AS t FROM {lineitem}), n AS (SELECT i, count(*) AS n FROM q GROUP BY i) SELECT a.i, b.i AS j, (SELECT count(*) FROM q x JOIN q y ON x.t = y.t WHERE x.i = a.i AND y.i = b.i)::INT AS k, (a.n + b.n - (SELECT count(*) FROM q x JOIN q y ON x.t = y.t WHERE x.i = a.i AND y.i = b.i))::INT AS u FROM n a JOIN n b ON b.i = a.i + 1")
_map = "SELECT p_brand, map_from_entries(collect_list(struct(p_type, c))) AS m, min(p_type) AS first FROM (SELECT p_brand, p_type, count(*) AS c FROM {part} GROUP BY 1, 2) q GROUP BY 1"
both(
    "op_map_support",
    f"SELECT p_brand, size(m) AS n, element_at(m, first) AS support, size(map_filter(m, (k, v) -> v > 1)) AS often FROM ({_map}) z",
    "SELECT p_brand, count(*)::INT AS n, arg_min(c, p_type) AS support, (count(*) FILTER (c > 1))::INT AS often FROM (SELECT p_brand, p_type, count(*) AS c FROM {part} GROUP BY 1, 2) q GROUP BY 1",
)
both(
    "op_nulls",
    "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, nullif(l.toxic, 0) AS toxic, l.quality <=> l.toxic AS same FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, nullif(l.toxic, 0) AS toxic, l.quality IS NOT DISTINCT FROM l.toxic AS same FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
)
_best = "SELECT s.i, b.best, b.n FROM {s} s, LATERAL (SELECT max(p.sim) AS best, count(*) AS n FROM {p} p WHERE p.i = s.i) b"
query("op_lateral", lambda p, s, d: s.sql(_best, p=p, s=_sup(s, d)), _best.replace("{p}", "tp").replace("{s}", "s"))
register(
    "op_pairs_udtf",
    lambda s, d: _udtf(s, d),
    f"WITH {sql_sample(W4, 'cosine', MU, 0.5)} SELECT least(CAST(i AS VARCHAR), CAST(j AS VARCHAR)) AS i, greatest(CAST(i AS VARCHAR), CAST(j AS VARCHAR)) AS j, k FROM sm",
)
#: Approximate distinct counts within four deviations of the promised one.
both(
    "op_approx_distinct",
    f"SELECT count(DISTINCT t) AS exact, abs(approx_count_distinct(t, 0.02) - count(DISTINCT t)) <= 0.08 * count(DISTINCT t) AS near FROM ({B4}) b",
    f"SELECT count(DISTINCT t) AS exact, true AS near FROM ({D4}) b",
)
register(
    "stream_supports",
    lambda s, d: streams.running_supports(s.read.parquet(f"{d}/events.parquet"), exact=True),
    "SELECT i, count(DISTINCT t) AS c FROM (SELECT concat(event_type, ':', CAST(CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10) AS INT) AS VARCHAR)) AS i, concat(user_id, '@', CAST(ts AS DATE)) AS t FROM events) q WHERE i IS NOT NULL GROUP BY i",
)
register(
    "stream_static_join",
    lambda s, d: streams.with_items(s.read.parquet(f"{d}/events.parquet"), streams.running_supports(s.read.parquet(f"{d}/events.parquet"), exact=True)).select("event_id", "i", "c"),
    "WITH e AS (SELECT event_id, concat(event_type, ':', CAST(CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10) AS INT) AS VARCHAR)) AS i, concat(user_id, '@', CAST(ts AS DATE)) AS t FROM events) "
    "SELECT event_id, e.i, c FROM e LEFT JOIN (SELECT i, count(DISTINCT t) AS c FROM e GROUP BY i) s ON e.i = s.i",
)
register("unpack_packed", lambda s, d: _unpack(s, d), f"WITH b AS ({D4}), s AS (SELECT i, count(*) AS c FROM b GROUP BY i) SELECT b.t, s.c, b.i FROM b JOIN s ON b.i = s.i")


def _unpack(s, d):
    from pairsample.operators import sampling
    from pairsample.sources.tables import unpack

    return unpack(sampling.pack(sampling.sample_rows(workloads.baskets(s, d, W4), "cosine")))


# --- streams, run over the whole table ----------------------------------------------------------------------------------------------

_ITEMS = "SELECT user_id, ts, concat(event_type, ':', CAST(CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10) AS INT) AS VARCHAR)) AS item FROM events"
_digest = lambda b: b.select("user_id", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))
register("stream_tumbling", lambda s, d: _digest(streams.window_baskets(s.read.parquet(f"{d}/events.parquet"), "1 day")), f"SELECT user_id, count(DISTINCT item)::INT AS n, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start FROM ({_ITEMS}) q GROUP BY user_id, date_trunc('day', ts)")
register(
    "stream_sliding", lambda s, d: _digest(streams.window_baskets(s.read.parquet(f"{d}/events.parquet"), "1 day", "6 hours")),
    f"SELECT user_id, count(DISTINCT item)::INT AS n, strftime(b, '%Y-%m-%d %H:%M:%S') AS start FROM (SELECT q.*, time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '2000-01-01') - to_hours(6 * o) AS b FROM ({_ITEMS}) q CROSS JOIN (SELECT unnest([0, 1, 2, 3]) AS o)) z GROUP BY user_id, b",
)
register(
    "stream_session", lambda s, d: _digest(streams.window_baskets(s.read.parquet(f"{d}/events.parquet"), "1 day", session_gap="2 hours")),
    f"SELECT user_id, count(DISTINCT item)::INT AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '2 hours' THEN 0 ELSE 1 END AS fresh FROM ({_ITEMS}) q) z) y GROUP BY user_id, g",
)


def thinning(s, d):
    """Candidates admitted under the supports of a few transactions, which lack many items, thinned to the final supports."""
    from pairsample.operators.baskets import support_counts

    all_ = workloads.baskets(s, d, W4)
    early = support_counts(all_.where("t % 500 = 1"))
    return streams.thin(streams.admit(all_, early, "cosine", MU, 0.3), support_counts(all_), "cosine", MU, 0.3)


register("stream_thinning_equals_batch", thinning, f"WITH {sql_sample(W4, 'cosine', MU, 0.3)} SELECT i, j, k, ci, cj FROM sm")
