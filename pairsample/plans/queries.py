"""Every method, baseline, measure, workload and experiment as a registered query, each with its check in DuckDB's SQL.

The checks of sampled queries are the quadratic form: a self-join of the baskets with the same MD5 draw and the same weight.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairsample import api
from pairsample.functions import draws, errors, measures
from pairsample.functions.measures import dbl, get
from pairsample.operators import adaptive, baselines, baskets as bk, refining, reporting, rules, sampling, seeds as many, strips, two_pass, weighted
from pairsample.operators.held import release
from pairsample.operators.tiles import numbered
from pairsample.plans import cost, planner
from pairsample.plans.registry import register
from pairsample.sources import tables, workloads
from pairsample.sources.workloads import baskets, duck, duck_view

MU, SEED = 15.0, 42
DUCK = draws.DUCKDB
W4, W5, W11 = "customer_suppliers", "customer_brandtype", "word_docs"


def local(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# --- SQL of the checks -------------------------------------------------------------------------------------------------------------


def sql_base(view: str, seed: int = SEED, scope: str = "transaction") -> str:
    return f"""b AS ({duck_view(view)}), s AS (SELECT i, count(*) AS c FROM b GROUP BY i), mm AS (SELECT count(DISTINCT t) AS m FROM b),
bs AS (SELECT b.t, b.i, s.c FROM b JOIN s ON b.i = s.i), e AS (SELECT t, i, c, {draws.draw_sql(seed, scope, DUCK)} AS r FROM bs)"""


def sql_sample(view: str, measure, mu: float, delta: float, seed: int = SEED, scope: str = "transaction") -> str:
    of = get(measure)
    return f"""{sql_base(view, seed, scope)}, p AS (SELECT x.i AS i, y.i AS j, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i))
CROSS JOIN mm WHERE {of.weight_sql(delta, 'x.c', 'y.c', 'mm.m')} * {dbl(mu)} > x.r), sm AS (SELECT i, j, count(*) AS k, ci, cj FROM p GROUP BY i, j, ci, cj)"""


def sql_report(measure, mu: float, delta: float, rule: str = "printed", cut: float | None = None) -> str:
    of = get(measure)
    exact, inter, sim = reporting.estimate_sql(of, mu, delta)
    return f"SELECT i, j, k, ci, cj, {exact} AS exact, {inter} AS est_inter, {sim} AS est_sim FROM sm CROSS JOIN mm WHERE {reporting.rule_sql(of, mu, delta, rule, cut)}"


def sql_pairs(view: str) -> str:
    """Every co-occurring pair, as ap."""
    return f"""{sql_base(view)}, ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5)"""


def sql_exact(view: str, measure, delta: float, extra: str = "") -> str:
    of = get(measure)
    return f"{sql_pairs(view)}, ex AS (SELECT i, j, k, ci, cj, {of.sim_sql()} AS raw FROM ap CROSS JOIN mm), tp AS (SELECT i, j, k, ci, cj, round(raw, 6) AS sim FROM ex WHERE raw >= {dbl(delta - 1e-12)})"


# --- measures ----------------------------------------------------------------------------------------------------------------------

#: Supports of parts and return flags in ``lineitem``, the rows that hold both, and all rows: each combination once.
GRID = (
    "SELECT DISTINCT ci, cj, k, m FROM (SELECT count(*) AS k, CAST(sum(count(*)) OVER (PARTITION BY l_partkey) AS BIGINT) AS ci, CAST(sum(count(*)) OVER (PARTITION BY l_returnflag) AS BIGINT) AS cj, "
    "CAST(sum(count(*)) OVER () AS BIGINT) AS m FROM {lineitem} GROUP BY l_partkey, l_returnflag) z"
)
DELTA_OF = {"cosine": 0.3, "jaccard": 0.2, "dice": 0.17, "all_confidence": 0.3, "overlap": 0.35, "lift": 1.05, "two_sided": 0.65}


def measure_sql(name: str) -> str:
    of = measures.MEASURES[name]
    s = of.sim("CAST(k AS DOUBLE)", "CAST(ci AS DOUBLE)", "CAST(cj AS DOUBLE)", "CAST(m AS DOUBLE)")
    weight = of.weight("CAST(ci AS DOUBLE)", "CAST(cj AS DOUBLE)", f"({s})", "CAST(m AS DOUBLE)")
    return f"SELECT ci, cj, k, round({s}, 6) AS sim, round(CAST(k AS DOUBLE) * {weight}, 6) AS one FROM ({GRID}) g"


for _name in ("lift", "cosine", "jaccard", "all_confidence", "dice", "overlap", "two_sided"):
    register(f"measure_{_name}", lambda spark, d, n=_name: tables.run_sql(spark, d, measure_sql(n)), duck(measure_sql(_name)))
_aliases = " UNION ALL ".join(f"SELECT '{n}' AS name, ci, cj, k, sim, one FROM ({measure_sql(n)}) q" for n in ("dice_std", "lift_raw"))
register("measure_aliases", lambda spark, d: tables.run_sql(spark, d, _aliases), duck(_aliases))


def _grid(spark: SparkSession, d: str) -> DataFrame:
    return tables.run_sql(spark, d, f"SELECT ci, cj, s FROM ({GRID}) g CROSS JOIN (SELECT 0.1D AS s UNION ALL SELECT 0.5D UNION ALL SELECT 0.9D) t").distinct()


def monotone_check(spark: SparkSession, d: str) -> DataFrame:
    found = None
    for name in sorted(set(measures.MEASURES)):
        one = measures.monotone_violations(name, _grid(spark, d)).agg(F.lit(name).alias("measure"), F.count("*").alias("violations"))
        found = one if found is None else found.unionByName(one)
    return found


register("measure_monotone_check", monotone_check, " UNION ALL ".join(f"SELECT '{n}' AS measure, 0::BIGINT AS violations" for n in sorted(set(measures.MEASURES))))


def mean_identity(spark: SparkSession, d: str) -> DataFrame:
    """Expected samples k f mu against the closed forms: mu s/delta, for the Jaccard mu s (1 + delta)/((1 + s) delta)."""
    rows = None
    for name in ("cosine", "jaccard", "all_confidence", "dice", "overlap", "lift"):
        of, delta = get(name), DELTA_OF[name]
        s = of.sim("CAST(k AS DOUBLE)", "CAST(ci AS DOUBLE)", "CAST(cj AS DOUBLE)", "CAST(m AS DOUBLE)")
        mean = f"CAST(k AS DOUBLE) * {of.weight('CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', dbl(delta), 'CAST(m AS DOUBLE)')} * {dbl(MU)}"
        closed = f"{dbl(MU)} * ({s}) / {dbl(delta)}" + (f" * (1e0 + {dbl(delta)}) / (1e0 + ({s}))" if name == "jaccard" else "")
        one = tables.run_sql(spark, d, f"SELECT '{name}' AS measure, ci, cj, k, round({mean}, 6) AS mean, round({closed}, 6) AS closed FROM ({GRID}) g")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def _mean_sql() -> str:
    parts = []
    for name in ("cosine", "jaccard", "all_confidence", "dice", "overlap", "lift"):
        of, delta = get(name), DELTA_OF[name]
        mean = f"CAST(k AS DOUBLE) * {of.weight('CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', dbl(delta), 'CAST(m AS DOUBLE)')} * {dbl(MU)}"
        parts.append(f"SELECT '{name}' AS measure, ci, cj, k, round({mean}, 6) AS mean, round({mean}, 6) AS closed FROM ({GRID}) g")
    return duck(" UNION ALL ".join(parts))


register("mean_samples_identity", mean_identity, _mean_sql())

# --- supports, draws, order --------------------------------------------------------------------------------------------------------

register("support_counts", lambda s, d: bk.support_counts(baskets(s, d, W4)), f"SELECT i, count(*) AS c FROM ({duck_view(W4)}) b GROUP BY i")
register("support_counts_sorted", lambda s, d: bk.support_counts(baskets(s, d, W4), "sort"), f"SELECT t, i, count(*) OVER (PARTITION BY i) AS c FROM ({duck_view(W4)}) b")
_stats = lambda v: f"""WITH b AS ({duck_view(v)}), z AS (SELECT t, count(*) AS b FROM b GROUP BY t), n AS (SELECT count(DISTINCT i) AS n FROM b)
SELECT count(*) AS m, any_value(n) AS n, sum(b)::BIGINT AS rows, round(sum(b) / count(*), 6) AS b, max(b) AS max_b, round(sum(b) / any_value(n), 6) AS sigma FROM z CROSS JOIN n"""  # noqa: E731
register("basket_stats", lambda s, d: bk.basket_stats(baskets(s, d, W4)), _stats(W4))
for _v in workloads.VIEWS:
    register(f"fig7_{_v}", lambda s, d, v=_v: bk.basket_stats(baskets(s, d, v)), _stats(_v))
register("support_prune", lambda s, d: bk.prune(baskets(s, d, "order_parts"), 20, 40), f"WITH b AS ({duck_view('order_parts')}) SELECT t, i FROM b WHERE i IN (SELECT i FROM b GROUP BY i HAVING count(*) BETWEEN 20 AND 40)")
register(
    "transaction_draw",
    lambda s, d: baskets(s, d, W4).select("t").distinct().select("t", F.round(F.expr(draws.draw_sql(SEED)), 9).alias("r")),
    f"SELECT t, round({draws.draw_sql(SEED, dialect=DUCK)}, 9) AS r FROM (SELECT DISTINCT t FROM ({duck_view(W4)}) b) q",
)
register("ordered_transactions", lambda s, d: sampling.ordered(bk.enrich(baskets(s, d, W4))), f"WITH {sql_base(W4)} SELECT t, i, c, CAST(row_number() OVER (PARTITION BY t ORDER BY c, i) AS INT) AS place FROM e")

# --- samples and reports -----------------------------------------------------------------------------------------------------------

SAMPLE = "SELECT i, j, k, ci, cj FROM sm"
for _name, _view in (("cosine", W4), ("jaccard", W4), ("dice", W4), ("all_confidence", W4), ("two_sided", W4), ("overlap", W5), ("lift", W5)):
    _d = DELTA_OF[_name]
    register(f"sample_{_name}", lambda s, d, n=_name, v=_view, x=_d: sampling.sample_pairs(baskets(s, d, v), n, MU, x, SEED), f"WITH {sql_sample(_view, _name, MU, _d)} {SAMPLE}")
    register(
        f"report_{_name}",
        lambda s, d, n=_name, v=_view, x=_d: reporting.report(sampling.sample_pairs(baskets(s, d, v), n, MU, x, SEED), n, MU, x, m=bk.transactions(baskets(s, d, v))),
        f"WITH {sql_sample(_view, _name, MU, _d)} {sql_report(_name, MU, _d)}",
    )
    register(f"exact_{_name}", lambda s, d, n=_name, v=_view, x=_d: baselines.exact_pairs(baskets(s, d, v), n, x), f"WITH {sql_exact(_view, _name, _d)} SELECT i, j, k, ci, cj, sim FROM tp")
register("sample_lift_rare", lambda s, d: sampling.sample_pairs(baskets(s, d, "order_parts"), "lift", MU, 40.0, SEED), f"WITH {sql_sample('order_parts', 'lift', MU, 40.0)} {SAMPLE}")
for _how in ("prefix", "arrow", "shuffle", "blocked", "selfjoin"):
    register(
        f"sample_{_how}", lambda s, d, h=_how: sampling.sample_pairs(baskets(s, d, W4), "cosine", MU, 0.3, SEED, strategy=h, block=16), f"WITH {sql_sample(W4, 'cosine', MU, 0.3)} {SAMPLE}"
    )
register("sample_anchor_draw", lambda s, d: sampling.sample_pairs(baskets(s, d, W4), "cosine", MU, 0.5, SEED, strategy="selfjoin", scope="anchor"), f"WITH {sql_sample(W4, 'cosine', MU, 0.5, scope='anchor')} {SAMPLE}")


def _w4(s, d, delta=0.3):
    return sampling.sample_pairs(baskets(s, d, W4), "cosine", MU, delta, SEED)


def _w5(s, d, delta=0.3):
    return sampling.sample_pairs(baskets(s, d, W5), "cosine", MU, delta, SEED)


_s4, _s5 = f"WITH {sql_sample(W4, 'cosine', MU, 0.3)}", f"WITH {sql_sample(W5, 'cosine', MU, 0.3)}"
register("report_strict", lambda s, d: reporting.report(_w4(s, d), "cosine", MU, 0.3, "strict"), f"{_s4} {sql_report('cosine', MU, 0.3, 'strict')}")
register("report_cut", lambda s, d: reporting.report(_w5(s, d), "cosine", MU, 0.3, cut=12.0), f"{_s5} {sql_report('cosine', MU, 0.3, cut=12.0)}")
register("report_all", lambda s, d: reporting.report(_w4(s, d), "cosine", MU, 0.3, "all"), f"{_s4} {sql_report('cosine', MU, 0.3, 'all')}")
register("estimates", lambda s, d: reporting.report(_w5(s, d), "cosine", MU, 0.3, "all").select("i", "j", "est_inter", "est_sim"), f"{_s5} SELECT i, j, est_inter, est_sim FROM ({sql_report('cosine', MU, 0.3, 'all')}) q")
register("find_pairs_cosine", lambda s, d: api.find_pairs(baskets(s, d, W4), "cosine", 0.3, MU, SEED, refine="none"), f"{_s4} {sql_report('cosine', MU, 0.3)}")
register(
    "find_pairs_exact", lambda s, d: api.find_pairs(baskets(s, d, W5), "cosine", 0.3, MU, SEED),
    f"WITH {sql_sample(W5, 'cosine', MU, 0.3)}, rp AS ({sql_report('cosine', MU, 0.3)}), ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5) "
    f"SELECT ap.i, ap.j, ap.k, ap.ci, ap.cj, round({get('cosine').sim_sql('ap.k', 'ap.ci', 'ap.cj')}, 6) AS sim FROM ap JOIN rp ON ap.i = rp.i AND ap.j = rp.j WHERE {get('cosine').sim_sql('ap.k', 'ap.ci', 'ap.cj')} >= {dbl(0.3 - 1e-12)}",
)
_verify = lambda v, x: f"""WITH {sql_sample(v, 'cosine', MU, x)}, rp AS ({sql_report('cosine', MU, x)}), ct AS (SELECT rp.i, rp.j, rp.ci, rp.cj, count(*) AS k FROM rp JOIN b x ON x.i = rp.i JOIN b y ON y.i = rp.j AND y.t = x.t GROUP BY 1, 2, 3, 4)
SELECT i, j, k, ci, cj, round({get('cosine').sim_sql()}, 6) AS sim FROM ct WHERE {get('cosine').sim_sql()} >= {dbl(x - 1e-12)}"""  # noqa: E731
register("verify_exact", lambda s, d: refining.verify_exact(reporting.report(_w4(s, d), "cosine", MU, 0.3), baskets(s, d, W4), "cosine", 0.3), _verify(W4, 0.3))
register("near_copies", lambda s, d: refining.verify_exact(reporting.report(sampling.sample_pairs(baskets(s, d, W11), "cosine", MU, 0.5, SEED, "tiles"), "cosine", MU, 0.5), baskets(s, d, W11), "cosine", 0.5), _verify(W11, 0.5))

# --- refining and variants ---------------------------------------------------------------------------------------------------------

SKETCH = 32


def sql_sketch(size: int = SKETCH) -> str:
    columns = ", ".join(f"min((x * {a} + {b}) % {refining.PRIME}) AS h{n}" for n, (a, b) in enumerate(refining.hash_family(size)))
    return f"sk AS (SELECT i, {columns} FROM (SELECT i, {refining.base_sql('t', DUCK)} AS x FROM b) q GROUP BY i)"


register("minhash_sketch", lambda s, d: refining.minhash_sketch(baskets(s, d, W11), 8), f"WITH b AS ({duck_view(W11)}), {sql_sketch(8)} SELECT * FROM sk")
_equal = " + ".join(f"CASE WHEN x.h{n} = y.h{n} THEN 1 ELSE 0 END" for n in range(SKETCH))
register(
    "filter_minhash",
    lambda s, d: refining.sampled_minhash(baskets(s, d, W11), SKETCH, "cosine", MU, 0.5, SEED),
    f"WITH {sql_sample(W11, 'cosine', MU, 0.5)}, {sql_sketch()}, q AS (SELECT sm.i, sm.j, sm.ci, sm.cj, ({_equal}) / {SKETCH}e0 AS est_jaccard FROM sm JOIN sk x ON sm.i = x.i JOIN sk y ON sm.j = y.i), "
    f"r AS (SELECT *, {get('cosine').sim('(est_jaccard * (CAST(ci AS DOUBLE) + CAST(cj AS DOUBLE)) / (1e0 + est_jaccard))', 'CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', '1e0')} AS z FROM q) SELECT i, j, round(est_jaccard, 6) AS est_jaccard, round(z, 6) AS est_sim FROM r WHERE z >= {dbl(0.5 - 1e-12)}",
)
register(
    "filter_smaller_set",
    lambda s, d: refining.filter_smaller_set(sampling.sample_pairs(baskets(s, d, W5), "overlap", MU, 0.35, SEED), baskets(s, d, W5), 0.5, "overlap", 0.35),
    f"WITH {sql_sample(W5, 'overlap', MU, 0.35)}, th AS (SELECT t, i FROM b WHERE {draws.uniform_sql('t', 7, DUCK)} < 0.5e0), q AS (SELECT sm.i, sm.j, sm.ci, sm.cj, count(*) AS probes, count(y.t) AS hits FROM sm JOIN th ON th.i = sm.i LEFT JOIN b y ON y.t = th.t AND y.i = sm.j GROUP BY 1, 2, 3, 4), "
    f"r AS (SELECT *, {get('overlap').sim('(CAST(hits AS DOUBLE) / CAST(probes AS DOUBLE) * CAST(ci AS DOUBLE))', 'CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', '1e0')} AS z FROM q) SELECT i, j, probes, hits, round(z, 6) AS est_sim FROM r WHERE z >= {dbl(0.35 - 1e-12)}",
)
register(
    "bloom_two_pass", lambda s, d: reporting.report(two_pass.sample_two_pass(baskets(s, d, W5), "cosine", MU, 0.3, SEED), "cosine", MU, 0.3), f"{_s5} {sql_report('cosine', MU, 0.3)}"
)
register("exact_two_pass", lambda s, d: two_pass.exact_two_pass(baskets(s, d, W5), "cosine", 0.3), f"WITH {sql_exact(W5, 'cosine', 0.3)} SELECT i, j, k, ci, cj, sim FROM tp")
register(
    "count_min_sketch",
    lambda s, d: two_pass.count_min_bounds(sampling.prefix_pairs(sampling.pack(sampling.sample_rows(baskets(s, d, W5), "cosine", SEED)), get("cosine"), MU, 0.3)),
    f"{_s5} SELECT count(*) AS pairs, 0::BIGINT AS too_few, true AS close FROM sm",
)

W3, RATE = "customer_parts", 0.5
register(
    "filter_smaller_set_unequal",
    lambda s, d: refining.sampled_smaller_set(baskets(s, d, W3), RATE, "overlap", MU, 0.3, SEED),
    f"WITH {sql_sample(W3, 'overlap', MU, 0.3)}, th AS (SELECT t, i FROM b WHERE {draws.uniform_sql('t', 7, DUCK)} < {dbl(RATE)}), "
    "q AS (SELECT sm.i, sm.j, sm.ci, sm.cj, count(*) AS probes, count(y.t) AS hits FROM sm JOIN th ON th.i = sm.i LEFT JOIN b y ON y.t = th.t AND y.i = sm.j GROUP BY 1, 2, 3, 4), "
    f"r AS (SELECT *, {get('overlap').sim('(CAST(hits AS DOUBLE) / CAST(probes AS DOUBLE) * CAST(ci AS DOUBLE))', 'CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', '1e0')} AS z FROM q) "
    f"SELECT i, j, probes, hits, round(z, 6) AS est_sim FROM r WHERE z >= {dbl(0.3 - 1e-12)}",
)
register(
    "count_min_two_pass", lambda s, d: reporting.report(two_pass.sample_count_min(baskets(s, d, W5), "cosine", MU, 0.3, SEED), "cosine", MU, 0.3), f"{_s5} {sql_report('cosine', MU, 0.3)}"
)

ONE_WEIGHT = "SELECT t, i, CAST(1 + i % 3 AS DOUBLE) AS w FROM ({v}) z"
QUANTITY = "SELECT o_custkey AS t, l_suppkey AS i, CAST(sum(l_quantity) AS DOUBLE) AS w FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY o_custkey, l_suppkey"


def sql_weighted(view: str, mu: float, delta: float) -> str:
    u = f"x.u * y.u * {dbl(mu / delta)}"
    return f"""WITH wb AS ({view}), cc AS (SELECT i, sum(w * w) AS c FROM wb GROUP BY i), nn AS (SELECT wb.t, wb.i, wb.w / sqrt(cc.c) AS u FROM wb JOIN cc ON wb.i = cc.i), e AS (SELECT t, i, u, {draws.draw_sql(SEED, dialect=DUCK)} AS r FROM nn),
p AS (SELECT x.i AS i, y.i AS j, {u} AS g FROM e x JOIN e y ON x.t = y.t AND x.i < y.i WHERE {u} > x.r), a AS (SELECT i, j, sum(greatest(1e0, g)) AS s, count(*) AS k, bool_and(g >= 1) AS certain FROM p GROUP BY i, j)
SELECT i, j, k, round(s * {dbl(delta)} / {dbl(mu)}, 6) AS est_sim FROM a WHERE s > {dbl(mu / 2)} OR (certain AND s >= {dbl(mu * (1 - 1e-12))})"""


register(
    "weighted_cosine",
    lambda s, d: weighted.report_weighted(weighted.sample_weighted(tables.run_sql(s, d, ONE_WEIGHT.replace("{v}", workloads.sql(W4))), MU, 0.3), MU, 0.3),
    sql_weighted(ONE_WEIGHT.replace("{v}", duck_view(W4)), MU, 0.3),
)
register(
    "weighted_occurrence", lambda s, d: weighted.report_weighted(weighted.sample_weighted(tables.run_sql(s, d, QUANTITY), MU, 0.3), MU, 0.3), sql_weighted(duck(QUANTITY), MU, 0.3)
)
register(
    "weighted_exact", lambda s, d: weighted.exact_weighted(tables.run_sql(s, d, QUANTITY), 0.3),
    f"WITH wb AS ({duck(QUANTITY)}), cc AS (SELECT i, sum(w * w) AS c FROM wb GROUP BY i), e AS (SELECT wb.t, wb.i, wb.w / sqrt(cc.c) AS u FROM wb JOIN cc ON wb.i = cc.i) SELECT x.i, y.i AS j, round(sum(x.u * y.u), 6) AS sim FROM e x JOIN e y ON x.t = y.t AND x.i < y.i GROUP BY 1, 2 HAVING sum(x.u * y.u) >= {dbl(0.3 - 1e-12)}",
)
BOTH = [("cosine", 0.3, 1.0), ("lift", 1.05, 1.0)]
AND, OR, BLEND = measures.all_of(BOTH), measures.any_of(BOTH), measures.blend([("cosine", 0.3, 0.5), ("lift", 1.05, 0.5)])
for _key, _of in (("composite_and", AND), ("composite_or", OR), ("composite_blend", BLEND)):
    register(
        _key, lambda s, d, o=_of: reporting.report(sampling.sample_pairs(baskets(s, d, W5), o, MU, 1.0, SEED), o, MU, 1.0, m=bk.transactions(baskets(s, d, W5))),
        f"WITH {sql_sample(W5, _of, MU, 1.0)} {sql_report(_of, MU, 1.0)}",
    )
_rare = measures.all_of([("cosine", 0.7, 1.0), ("lift", 2.0, 1.0)], "and_rare")
register("composite_and_documents", lambda s, d: sampling.sample_pairs(baskets(s, d, W11), _rare, MU, 1.0, SEED, "tiles"), f"WITH {sql_sample(W11, _rare, MU, 1.0)} {SAMPLE}")


def sql_rules(view: str, pairs: str, conf: float) -> str:
    return f"SELECT lhs, rhs, k, round(k / c, 6) AS confidence FROM (SELECT i AS lhs, j AS rhs, k, ci AS c FROM {pairs} UNION ALL SELECT j, i, k, cj FROM {pairs}) q WHERE k / c >= {dbl(conf - 1e-12)}"


register("rules_exact", lambda s, d: rules.rules_exact(baskets(s, d, W5), 0.35), f"WITH {sql_exact(W5, 'overlap', 0.35)} {sql_rules(W5, 'tp', 0.35)}")
register(
    "rules_sampled", lambda s, d: rules.rules_sampled(baskets(s, d, W5), 0.35),
    f"WITH {sql_sample(W5, 'overlap', MU, 0.35)}, rp AS ({sql_report('overlap', MU, 0.35)}), ct AS (SELECT rp.i, rp.j, rp.ci, rp.cj, count(*) AS k FROM rp JOIN b x ON x.i = rp.i JOIN b y ON y.i = rp.j AND y.t = x.t GROUP BY 1, 2, 3, 4), "
    f"tp AS (SELECT * FROM ct WHERE {get('overlap').sim_sql()} >= {dbl(0.35 - 1e-12)}) {sql_rules(W5, 'tp', 0.35)}",
)

# --- adaptive ----------------------------------------------------------------------------------------------------------------------


def sql_levels(view: str, measure: str, mu: float, floor: float) -> str:
    of = get(measure)
    star = f"coalesce(CASE WHEN x.r > 0e0 THEN {of.solve_sql(f'(x.r / {dbl(mu)})', 'x.c', 'y.c', 'mm.m')} END, {adaptive.INFINITE})"
    return f"""{sql_base(view)}, oc AS (SELECT * FROM (SELECT x.i AS i, y.i AS j, x.c AS ci, y.c AS cj, {star} AS s_star FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) CROSS JOIN mm) q WHERE s_star > {dbl(floor)}),
rk AS (SELECT *, row_number() OVER (PARTITION BY i, j ORDER BY s_star DESC) AS k FROM oc),
lv AS (SELECT i, j, greatest(coalesce(max(CASE WHEN k = {int(mu // 2) + 1} THEN s_star END), 0e0), max(least(s_star, {of.sim_sql()}))) AS level FROM rk CROSS JOIN mm GROUP BY i, j)"""


register("adaptive_topk", lambda s, d: adaptive.top_pairs(baskets(s, d, W5), "cosine", MU, 100), f"WITH {sql_levels(W5, 'cosine', MU, 0.05)} SELECT i, j, round(level, 6) AS level FROM lv ORDER BY lv.level DESC, i, j LIMIT 100")
register("calibrate_delta", lambda s, d: adaptive.calibrate_delta(baskets(s, d, W4), "cosine", MU, 100), f"WITH {sql_levels(W4, 'cosine', MU, 0.05)} SELECT min(level) AS delta, count(*) AS outputs FROM (SELECT round(level, 6) AS level FROM lv ORDER BY lv.level DESC, i, j LIMIT 100) q")
register(
    "adaptive_consistency", lambda s, d: adaptive.levels(adaptive.occurrences(baskets(s, d, W5), "cosine", MU, 0.2), "cosine", MU).where("level > 0.3").select("i", "j"),
    f"{_s5} SELECT i, j FROM sm WHERE {reporting.rule_sql(get('cosine'), MU, 0.3)}",
)
ENOUGH, BANDS = 5000, (0.5, 0.25, 0.125, 0.0625)
register(
    "adaptive_enough", lambda s, d: adaptive.enough_pairs(baskets(s, d, W4), "cosine", MU, ENOUGH, least=BANDS[-1]).select("i", "j", F.round("level", 6).alias("level")),
    f"""WITH {sql_levels(W4, 'cosine', MU, BANDS[-1])}, stop AS (SELECT coalesce(max(CASE WHEN n >= {ENOUGH} THEN f END), {dbl(BANDS[-1])}) AS f FROM
({' UNION ALL '.join(f"SELECT {dbl(b)} AS f, count(*) AS n FROM lv WHERE level > {dbl(b)}" for b in BANDS)}) x) SELECT i, j, round(level, 6) AS level FROM lv, stop WHERE level > stop.f""",
)
register("adaptive_frontier", lambda s, d: adaptive.frontier(baskets(s, d, W4)), f"WITH {sql_base(W4)} SELECT t, i, j FROM (SELECT t, i, lead(i) OVER (PARTITION BY t ORDER BY c, i) AS j FROM e) q WHERE j IS NOT NULL")

# --- baselines ---------------------------------------------------------------------------------------------------------------------

register("exact_pairs", lambda s, d: baselines.all_pairs(baskets(s, d, W4)), f"WITH {sql_pairs(W4)} SELECT i, j, k, ci, cj FROM ap")
_pruned = f"WITH {sql_exact(W5, 'cosine', 0.3)}, big AS (SELECT i FROM s WHERE c >= 345)"
register("exact_pruned", lambda s, d: baselines.exact_pruned(baskets(s, d, W5), "cosine", 0.3, 345), f"{_pruned} SELECT i, j, k, ci, cj, sim FROM tp WHERE i IN (SELECT i FROM big) AND j IN (SELECT i FROM big)")
register("pruning_loss", lambda s, d: baselines.pruning_loss(baskets(s, d, W5), "cosine", 0.3, 345), f"{_pruned} SELECT i, j, k, ci, cj, sim FROM tp WHERE NOT (i IN (SELECT i FROM big) AND j IN (SELECT i FROM big))")
_equal16 = " + ".join(f"CASE WHEN x.h{n} = y.h{n} THEN 1 ELSE 0 END" for n in range(16))
register(
    "signature_all_pairs", lambda s, d: baselines.signature_all_pairs(baskets(s, d, W4), 16, 0.3),
    f"WITH b AS ({duck_view(W4)}), {sql_sketch(16)}, q AS (SELECT x.i AS i, y.i AS j, ({_equal16}) / 16e0 AS z FROM sk x JOIN sk y ON x.i < y.i) SELECT i, j, round(z, 6) AS est_jaccard FROM q WHERE z >= {dbl(0.3 - 1e-12)}",
)
LSH_AT, LSH_BITS, LSH_BANDS, LSH_DIM = 0.45, 6, 24, 64


def sql_hyperplanes(dim: int) -> str:
    planes = baselines.planes(LSH_BANDS, LSH_BITS, dim)
    rows = ", ".join(f"({b}, {k}, {[float(v) for v in planes[b, k]]}::DOUBLE[])" for b in range(LSH_BANDS) for k in range(LSH_BITS))
    return f"""WITH pl(band, bit, plane) AS (VALUES {rows}), v AS (SELECT vec_id AS v, embedding::DOUBLE[] AS x FROM embeddings),
kk AS (SELECT v, band, string_agg(CASE WHEN list_inner_product(x, plane) > 0 THEN '1' ELSE '0' END, '' ORDER BY bit) AS key FROM v CROSS JOIN pl GROUP BY v, band),
pr AS (SELECT DISTINCT a.v AS i, b.v AS j FROM kk a JOIN kk b ON a.band = b.band AND a.key = b.key AND a.v < b.v)
SELECT i, j, round(list_cosine_similarity(x.x, y.x), 6) AS cos FROM pr JOIN v x ON x.v = pr.i JOIN v y ON y.v = pr.j WHERE list_cosine_similarity(x.x, y.x) >= {dbl(LSH_AT)}"""


register("lsh_cosine", lambda s, d: baselines.hyperplane_pairs(tables.table(s, d, "embeddings"), "vec_id", "embedding", LSH_BITS, LSH_BANDS, LSH_AT), sql_hyperplanes(LSH_DIM))
register(
    "uniform_sample", lambda s, d: baselines.uniform_sample(baskets(s, d, W4), 0.1),
    f"WITH {sql_base(W4)} SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) WHERE x.r < 0.1e0 GROUP BY 1, 2, 4, 5",
)

# --- costs and errors --------------------------------------------------------------------------------------------------------------


def sql_cost(view: str, measure, mu: float, delta: float) -> str:
    of = get(measure)
    return f"""{sql_pairs(view)}, q AS (SELECT k, least(1e0, {of.weight_sql(delta)} * {dbl(mu)}) AS p, {of.sim_sql()} AS z, ci, cj FROM ap CROSS JOIN mm),
su AS (SELECT coalesce(sum(k * p), 0) AS inserted, coalesce(sum(1 - pow(1 - p, k)), 0) AS entries, count(*) AS pairs, count(*) FILTER (z >= {dbl(delta - 1e-12)}) AS output, coalesce(sum(z), 0) AS sum_sim, sum(k / ci + k / cj) AS two_sided FROM q),
ba AS (SELECT (SELECT count(*) FROM b) AS rows, (SELECT count(*) FROM s) AS n, (SELECT sum(x * (x - 1) / 2) FROM (SELECT count(*) AS x FROM b GROUP BY t) z) AS all_pairs)"""


COST = """SELECT round(rows + inserted, 3) AS time_s, round((rows + all_pairs)::DOUBLE, 3) AS time_e, round((rows + all_pairs)::DOUBLE / (rows + inserted), 6) AS time_ratio,
round(n + entries, 3) AS space_s, round((n + pairs)::DOUBLE, 3) AS space_e, round((n + pairs)::DOUBLE / (n + entries), 6) AS space_ratio, output"""
for _v, _x in workloads.DELTAS.items():
    register(f"fig8_{_v}", lambda s, d, v=_v, x=_x: cost.compare(baskets(s, d, v), "cosine", MU, x), f"WITH {sql_cost(_v, 'cosine', MU, _x)} {COST} FROM su CROSS JOIN ba")


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _one_by_one(spark: SparkSession, of: Callable[[str], DataFrame], names: tuple[str, ...]) -> DataFrame:
    """The rows of all names, those of one (a few figures) collected before the next is planned: the driver holds the items of one view at a time."""
    rows, schema = [], None
    for name in names:
        part = of(name)
        rows, schema = rows + part.collect(), part.schema
        del part
        release(spark)
    return spark.createDataFrame(rows, schema)


SIX = ("cosine", "jaccard", "dice", "all_confidence", "overlap", "lift")
register(
    "fig8_measures", lambda s, d: _union([cost.compare(baskets(s, d, W5), n, MU, DELTA_OF[n]).withColumn("measure", F.lit(n)) for n in SIX]),
    " UNION ALL ".join(f"SELECT * FROM (WITH {sql_cost(W5, n, MU, DELTA_OF[n])} {COST}, '{n}' AS measure FROM su CROSS JOIN ba)" for n in SIX),
)
POINTS = tuple(workloads.DELTAS)
register(
    "fig9_points", lambda s, d: _one_by_one(s, lambda v: cost.compare(baskets(s, d, v), "cosine", MU, workloads.DELTAS[v]).select(F.lit(v).alias("view"), "time_s", "time_e", "space_s", "space_e"), POINTS),
    " UNION ALL ".join(f"SELECT '{v}' AS view, time_s, time_e, space_s, space_e FROM (WITH {sql_cost(v, 'cosine', MU, workloads.DELTAS[v])} {COST} FROM su CROSS JOIN ba)" for v in POINTS),
)
DELTA_SWEEP, MU_SWEEP = (0.1, 0.2, 0.3, 0.5, 0.7, 0.9), (3.0, 5.0, 10.0, 15.0, 20.0, 30.0)
register(
    "sweep_delta", lambda s, d: _union([cost.compare(baskets(s, d, W4), "cosine", MU, x).withColumn("delta", F.lit(x)) for x in DELTA_SWEEP]),
    " UNION ALL ".join(f"SELECT * FROM (WITH {sql_cost(W4, 'cosine', MU, x)} {COST}, {dbl(x)} AS delta FROM su CROSS JOIN ba)" for x in DELTA_SWEEP),
)
register(
    "sweep_mu", lambda s, d: _union([cost.compare(baskets(s, d, W4), "cosine", x, 0.5).withColumn("mu", F.lit(x)) for x in MU_SWEEP]),
    " UNION ALL ".join(f"SELECT * FROM (WITH {sql_cost(W4, 'cosine', x, 0.5)} {COST}, {dbl(x)} AS mu FROM su CROSS JOIN ba)" for x in MU_SWEEP),
)
register(
    "cost_observed", lambda s, d: cost.observed(baskets(s, d, W4), _w4(s, d, 0.5)),
    f"WITH {sql_sample(W4, 'cosine', MU, 0.5)} SELECT ((SELECT count(*) FROM b) + coalesce(sum(k), 0))::BIGINT AS time_s, ((SELECT count(*) FROM s) + count(*))::BIGINT AS space_s FROM sm",
)
register(
    "cost_exact", lambda s, d: cost.exact(baskets(s, d, W4)),
    f"WITH {sql_pairs(W4)} SELECT ((SELECT count(*) FROM b) + (SELECT sum(x * (x - 1) // 2) FROM (SELECT count(*) AS x FROM b GROUP BY t) z))::BIGINT AS time_e, ((SELECT count(*) FROM s) + (SELECT count(*) FROM ap))::BIGINT AS space_e",
)
register(
    "cost_expected", lambda s, d: cost.pair_sums(baskets(s, d, W4), "cosine", MU, 0.5).select(F.round("inserted", 3).alias("inserted"), F.round("entries", 3).alias("entries")),
    f"WITH {sql_cost(W4, 'cosine', MU, 0.5)} SELECT round(inserted, 3) AS inserted, round(entries, 3) AS entries FROM su",
)
_logn, _b = "log2(n::DOUBLE)", "(rows / mm.m)"
BOUNDS = {
    "ram": (f"round(rows * {_logn} + {dbl(MU / 0.5)} * sum_sim, 3)", ["ram"]),
    "corollary": (f"round(rows * {_logn} + {dbl(MU)} * n * n, 3) AS corollary, round(2 * sum_sim / (n * (n - 1)), 9)", ["corollary", "average_similarity"]),
    "gain": (f"round({_b} * least(1 / log2({_b}), (rows / n) / ({dbl(MU)} * n)), 6) AS gain, CASE WHEN rows / n < {dbl(MU)} * n / log2({_b}) THEN 'pairs' ELSE 'counting' END", ["gain", "dominant"]),
    "independent": (f"round(two_sided, 3) AS two_sided, round((n - 1) * {_b}, 3)", ["two_sided", "independent"]),
    "output": (f"round((rows + output)::DOUBLE, 3) AS lower, round(rows * {_logn} + {dbl(MU)} * output, 3)", ["lower", "output_bound"]),
    "io": (f"round((rows + inserted) / 1024e0 * greatest(1e0, ln((rows + inserted) / 65536e0) / ln(64e0)), 3)", ["io"]),
}
for _key, (_text, _cols) in BOUNDS.items():
    register(
        f"bound_{_key}", lambda s, d, c=_cols: cost.bounds(baskets(s, d, "customer_parts"), "cosine", MU, 0.5).select(*[F.col(x).cast("double").alias(x) if x != "dominant" else x for x in c]),
        f"WITH {sql_cost('customer_parts', 'cosine', MU, 0.5)} SELECT {_text} AS {_cols[-1]} FROM su CROSS JOIN ba CROSS JOIN mm",
    )
register(
    "bound_two_sided", lambda s, d: baselines.all_pairs(baskets(s, d, W5)).select(F.expr(get("two_sided").sim_sql()).alias("z"), *[F.expr(get(n).sim_sql()).alias(n) for n in ("cosine", "jaccard", "all_confidence", "dice", "overlap")])
    .agg(*[F.count_if(F.col(n) > F.col("z") + 1e-9).alias(n) for n in ("cosine", "jaccard", "all_confidence", "dice", "overlap")]),
    "SELECT " + ", ".join(f"0::BIGINT AS {n}" for n in ("cosine", "jaccard", "all_confidence", "dice", "overlap")),
)
#: The chance of at most ``cut`` successes among k, term by term from logarithms of factorials.
_binomial = lambda k, p, cut: (
    f"(CASE WHEN {p} >= 1e0 THEN (CASE WHEN {k} <= {cut} THEN 1e0 ELSE 0e0 END) ELSE (SELECT sum(exp(lgamma(CAST({k} AS DOUBLE) + 1) - lgamma(CAST(x AS DOUBLE) + 1) - lgamma(CAST({k} - x AS DOUBLE) + 1) "
    f"+ x * ln({p}) + ({k} - x) * ln(1e0 - least({p}, 0.999999999e0)))) FROM unnest(range(0, CAST(least({cut}, {k}) AS INT) + 1)) u(x)) END)"
)
register(
    "expected_output", lambda s, d: cost.expected_output(baskets(s, d, W5), "cosine", MU, 0.3),
    f"WITH {sql_pairs(W5)}, q AS (SELECT k, ci, cj, least(1e0, {get('cosine').weight_sql(0.3)} * {dbl(MU)}) AS p, {get('cosine').sim_sql()} AS z FROM ap CROSS JOIN mm), "
    f"g AS (SELECT z, CASE WHEN p >= 1e0 THEN (CASE WHEN {reporting.rule_sql(get('cosine'), MU, 0.3)} THEN 1e0 ELSE 0e0 END) ELSE 1e0 - {_binomial('q.k', 'q.p', 7)} END AS c FROM q) "
    f"SELECT round(coalesce(sum(c) FILTER (z >= {dbl(0.3 - 1e-12)}), 0), 3) AS true_reports, round(coalesce(sum(c) FILTER (z < {dbl(0.3 - 1e-12)}), 0), 3) AS false_reports FROM g",
)
_pois = lambda mean, cut: f"(SELECT sum(exp(-{mean} + k * ln({mean}) - (CASE WHEN k < 1 THEN 0 ELSE lgamma(k + 1) END))) FROM unnest(range(0, CAST(floor({cut}) AS INT) + 1)) u(k))"
#: Means, ratios to the threshold and numbers of trials as ``lineitem`` holds them: its quantities, these over their middle, and the rows of its parts.
_mus = "SELECT DISTINCT CAST(l_quantity AS DOUBLE) AS mu FROM {lineitem}"
_ratios = "SELECT DISTINCT CAST(l_quantity AS DOUBLE) / 25e0 AS ratio FROM {lineitem}"
_trials = "SELECT DISTINCT CAST(count(*) AS INT) AS k FROM {lineitem} GROUP BY l_partkey HAVING count(*) >= 15"
register(
    "fig5_mu_epsilon", lambda s, d: errors.misses(tables.run_sql(s, d, _mus)),
    f"SELECT mu, round(exp(-mu / 8), 9) AS proven, round({_pois('mu', 'mu / 2')}, 9) AS standard, round(exp(-mu), 15) AS whole FROM ({duck(_mus)}) q",
)
register(
    "fig6_curves", lambda s, d: errors.count_chances(tables.run_sql(s, d, _ratios), MU),
    f"SELECT round(ratio, 6) AS ratio, k::INT AS k, round(exp(-(ratio * 15e0) + k * ln(ratio * 15e0) - (CASE WHEN k < 1 THEN 0 ELSE lgamma(k + 1) END)), 9) AS probability FROM ({duck(_ratios)}) a CROSS JOIN (SELECT unnest(range(0, 41)) AS k) c",
)
register(
    "fp_curve", lambda s, d: tables.run_sql(s, d, _ratios).select(F.round("ratio", 6).alias("ratio"), F.round(1 - errors.poisson_cdf("(ratio * 15e0)", "7.5e0"), 9).alias("reported")),
    f"SELECT round(ratio, 6) AS ratio, round(1 - {_pois('(ratio * 15e0)', 7.5)}, 9) AS reported FROM ({duck(_ratios)}) q",
)
register(
    "fn_binomial", lambda s, d: tables.run_sql(s, d, _trials).select("k", F.round(F.expr(errors.binomial_below_sql("k", "15e0 / k", 7)), 9).alias("missed")),
    f"SELECT k, round({_binomial('q.k', '(15e0 / q.k)', 7)}, 9) AS missed FROM ({duck(_trials)}) q",
)
_conf = """, a AS (SELECT rp.i AS ri, tp.i AS ti FROM rp FULL OUTER JOIN tp ON rp.i = tp.i AND rp.j = tp.j), c AS (SELECT count(*) FILTER (ri IS NOT NULL AND ti IS NOT NULL) AS tp, count(*) FILTER (ti IS NULL) AS fp, count(*) FILTER (ri IS NULL) AS fn FROM a)
SELECT tp, fp, fn, round(tp / (tp + fn), 6) AS recall, round(tp / (tp + fp), 6) AS precision FROM c"""
register(
    "confusion_cosine", lambda s, d: cost.confusion(reporting.report(_w5(s, d), "cosine", MU, 0.3), baselines.exact_pairs(baskets(s, d, W5), "cosine", 0.3)),
    f"WITH {sql_sample(W5, 'cosine', MU, 0.3)}, rp AS ({sql_report('cosine', MU, 0.3)}), ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5), "
    f"tp AS (SELECT i, j FROM ap WHERE {get('cosine').sim_sql()} >= {dbl(0.3 - 1e-12)}){_conf}",
)


def many_seeds(s: SparkSession, d: str, view: str, delta: float, seeds: int) -> DataFrame:
    """(seed, i, j, k, ci, cj): the samples of several seeds in one plan."""
    rows = bk.enrich(baskets(s, d, view)).crossJoin(F.broadcast(s.range(1, seeds + 1).withColumnRenamed("id", "seed")))
    digest = F.substring(F.md5(F.concat_ws(":", F.col("seed").cast("string"), F.col("t").cast("string"))), 1, 8)
    drawn = rows.select(F.struct("seed", "t").alias("t"), "i", "c", (F.conv(digest, 16, 10).cast("double") / 4294967296.0).alias("r"), F.lit(1).cast("long").alias("m"))
    pairs = sampling.prefix_pairs(sampling.pack(drawn), get("cosine"), MU, delta)
    return pairs.groupBy(F.col("t.seed").alias("seed"), "i", "j").agg(F.count("*").alias("k"), F.first("ci").alias("ci"), F.first("cj").alias("cj"))


def sql_seeds(view: str, delta: float, seeds: int) -> str:
    digest = "substring(md5(concat(CAST(seed AS VARCHAR), ':', CAST(t AS VARCHAR))), 1, 8)"
    return f"""{sql_base(view)}, es AS (SELECT seed, t, i, c, CAST(CAST(concat('0x', {digest}) AS BIGINT) AS DOUBLE) / 4294967296e0 AS r FROM e CROSS JOIN (SELECT unnest(range(1, {seeds + 1})) AS seed) q),
ms AS (SELECT x.seed, x.i AS i, y.i AS j, x.c AS ci, y.c AS cj, count(*) AS k FROM es x JOIN es y ON x.seed = y.seed AND x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) WHERE {get('cosine').weight_sql(delta, 'x.c', 'y.c')} * {dbl(MU)} > x.r GROUP BY 1, 2, 3, 4, 5)"""


register(
    "concentration", lambda s, d: many.inserted_by_seed(baskets(s, d, W4), "cosine", MU, 0.5, range(1, 21)).agg(F.round(F.avg("inserted"), 3).alias("mean"), F.round(F.stddev("inserted"), 3).alias("deviation")),
    f"WITH {sql_seeds(W4, 0.5, 20)} SELECT round(avg(n), 3) AS mean, round(stddev(n), 3) AS deviation FROM (SELECT seed, sum(k)::DOUBLE AS n FROM ms GROUP BY seed) q",
)
SEEDS, MANY = 10, 50


def _missed(s: SparkSession, d: str, view: str, delta: float) -> DataFrame:
    items = numbered(baskets(s, d, view), strips.MAX_ITEMS)
    if items is not None:
        return many.missed_by_seed(baskets(s, d, view), items, "cosine", MU, delta, range(1, MANY + 1))
    sample = many_seeds(s, d, view, delta, MANY)
    true_pairs = baselines.exact_pairs(baskets(s, d, view), "cosine", delta).select("i", "j", F.lit(1).alias("t")).crossJoin(s.range(1, MANY + 1).withColumnRenamed("id", "seed"))
    reported = sample.where(reporting.rule_sql(get("cosine"), MU, delta)).select("seed", "i", "j", F.lit(1).alias("r"))
    return true_pairs.join(reported, ["seed", "i", "j"], "left").groupBy("seed").agg(F.count("*").alias("true_pairs"), F.count_if(F.col("r").isNull()).alias("missed"))


def sql_missed(view: str, delta: float) -> str:
    return (
        f"WITH {sql_seeds(view, delta, MANY)}, {ALL_PAIRS}, tp AS (SELECT i, j FROM ap WHERE {get('cosine').sim_sql()} >= {dbl(delta - 1e-12)}), rp AS (SELECT seed, i, j FROM ms WHERE {reporting.rule_sql(get('cosine'), MU, delta)}) "
        f"SELECT z.seed::BIGINT AS seed, count(*) AS true_pairs, count(*) FILTER (rp.i IS NULL) AS missed FROM tp CROSS JOIN (SELECT unnest(range(1, {MANY + 1})) AS seed) z LEFT JOIN rp ON rp.seed = z.seed AND rp.i = tp.i AND rp.j = tp.j GROUP BY 1"
    )


ALL_PAIRS = "ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5)"
register("observed_fn", lambda s, d: _missed(s, d, W5, 0.25), sql_missed(W5, 0.25))
register("observed_fn_texts", lambda s, d: _missed(s, d, "run_texts", 0.3), sql_missed("run_texts", 0.3))
register("observed_fn_suppliers", lambda s, d: _missed(s, d, W4, 0.3), sql_missed(W4, 0.3))


def _false(s: SparkSession, d: str) -> DataFrame:
    """Share of all co-occurring pairs that is reported, by tenths of similarity over the threshold."""
    items = numbered(baskets(s, d, W4), strips.MAX_ITEMS)
    if items is not None:
        found = many.reports_by_similarity(baskets(s, d, W4), items, "cosine", MU, 0.5, range(1, SEEDS + 1))
        return found.withColumn("share", F.round(F.col("reports") / F.col("pairs") / SEEDS, 6))
    pairs = baselines.all_pairs(baskets(s, d, W4)).withColumn("bucket", F.floor(F.expr(get("cosine").sim_sql()) / 0.5 * 10).cast("int"))
    reported = many_seeds(s, d, W4, 0.5, SEEDS).where(reporting.rule_sql(get("cosine"), MU, 0.5)).groupBy("i", "j").agg(F.count("*").alias("times"))
    each = pairs.select("i", "j", "bucket").join(reported, ["i", "j"], "left").groupBy("bucket")
    return each.agg(F.count("*").alias("pairs"), F.coalesce(F.sum("times"), F.lit(0)).alias("reports")).withColumn("share", F.round(F.col("reports") / F.col("pairs") / SEEDS, 6))


register(
    "observed_fp", _false,
    f"WITH {sql_seeds(W4, 0.5, SEEDS)}, ap AS (SELECT x.i AS i, y.i AS j, count(*) AS k, x.c AS ci, y.c AS cj FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2, 4, 5), "
    f"rp AS (SELECT i, j, count(*) AS times FROM ms WHERE {reporting.rule_sql(get('cosine'), MU, 0.5)} GROUP BY 1, 2), q AS (SELECT CAST(floor({get('cosine').sim_sql('ap.k', 'ap.ci', 'ap.cj')} / 0.5e0 * 10) AS INT) AS bucket, times FROM ap LEFT JOIN rp ON ap.i = rp.i AND ap.j = rp.j) "
    f"SELECT bucket, count(*) AS pairs, coalesce(sum(times), 0)::BIGINT AS reports, round(coalesce(sum(times), 0) / count(*) / {SEEDS}, 6) AS share FROM q GROUP BY bucket",
)
register(
    "lsh_ratio", lambda s, d: cost.compare(baskets(s, d, "order_parts"), "cosine", MU, 0.5).crossJoin(bk.basket_stats(baskets(s, d, "order_parts"))).select(F.round(F.col("n") * (F.col("n") - 1) / 2 / F.col("time_s"), 6).alias("signatures_over_hashes")),
    f"WITH {sql_cost('order_parts', 'cosine', MU, 0.5)}, cr AS ({COST}, n FROM su CROSS JOIN ba) SELECT round(n * (n - 1) / 2 / time_s, 6) AS signatures_over_hashes FROM cr",
)
register(
    "phase_share", lambda s, d: cost.base(baskets(s, d, W4)).crossJoin(cost.pair_sums(baskets(s, d, W4), "cosine", MU, 0.5)).select("rows", F.round("inserted", 3).alias("inserted"), F.round(F.col("inserted") / (F.col("rows") + F.col("inserted")), 6).alias("share")),
    f"WITH {sql_cost(W4, 'cosine', MU, 0.5)} SELECT rows, round(inserted, 3) AS inserted, round(inserted / (rows + inserted), 6) AS share FROM su CROSS JOIN ba",
)
register(
    "speedup_drivers", lambda s, d: _one_by_one(s, lambda v: cost.compare(baskets(s, d, v), "cosine", MU, 0.5).crossJoin(bk.basket_stats(baskets(s, d, v))).select(F.lit(v).alias("view"), "b", "sigma", "time_ratio"), POINTS),
    " UNION ALL ".join(f"SELECT '{v}' AS view, b, sigma, time_ratio FROM (WITH {sql_cost(v, 'cosine', MU, 0.5)} {COST} FROM su CROSS JOIN ba) q CROSS JOIN ({_stats(v)}) z" for v in POINTS),
)
register(
    "early_stop_work", lambda s, d: sampling.count_tests(sampling.pack(sampling.sample_rows(baskets(s, d, W4), "cosine", SEED)), get("cosine"), MU, 0.5),
    f"WITH {sql_base(W4)}, q AS (SELECT x.t, x.i, count(*) AS n, count(*) FILTER ({get('cosine').weight_sql(0.5, 'x.c', 'y.c')} * {dbl(MU)} > x.r) AS taken FROM e x JOIN e y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) GROUP BY 1, 2) "
    "SELECT sum(n)::BIGINT AS pairs, sum(taken)::BIGINT AS inserted, sum(least(n, taken + 1))::BIGINT AS tests_with_stop FROM q",
)


def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """One transaction of items 1 to 6 with given supports: the pairs taken at two draws."""
    supports = {1: 60, 2: 60, 3: 50, 4: 5, 5: 5, 6: 3}
    rows = local(spark, [(r, i, c) for r in (0.9, 0.91) for i, c in supports.items()], "r double, i long, c long").select(F.col("r").alias("t"), "i", "c", "r", F.lit(1).cast("long").alias("m"))
    return sampling.prefix_pairs(sampling.pack(rows), get("cosine"), 10.0, 0.7).select(F.col("t").alias("r"), F.greatest("i", "j").alias("i"), F.least("i", "j").alias("j"))


_at90, _at91 = [(6, 5), (6, 4), (6, 3), (6, 2), (6, 1), (5, 4), (5, 3), (4, 3)], [(6, 5), (6, 4), (6, 3), (6, 2), (6, 1), (5, 4)]
register("worked_example", worked_example, " UNION ALL ".join(f"SELECT {r}::DOUBLE AS r, {i}::BIGINT AS i, {j}::BIGINT AS j" for r, ps in ((0.9, _at90), (0.91, _at91)) for i, j in ps))
register(
    "plan_estimate", lambda s, d: planner.estimate(baskets(s, d, W4), "cosine", MU, 0.5, 0.2),
    f"WITH {sql_base(W4)}, th AS (SELECT * FROM e WHERE {draws.uniform_sql('t', SEED + 1, DUCK)} < 0.2e0), q AS (SELECT count(*) AS n FROM th x JOIN th y ON x.t = y.t AND (x.c < y.c OR (x.c = y.c AND x.i < y.i)) "
    f"WHERE {get('cosine').weight_sql(0.5, 'x.c', 'y.c')} * {dbl(MU)} > x.r) SELECT (SELECT count(DISTINCT t) FROM th) AS looked_at, n AS inserted, round(n / 0.2e0, 3) AS estimate FROM q",
)
