"""Basket views over the given tables, as SQL with marks for the tables and for the few spellings in which engines differ."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pairsample.sources.tables import NAMES, run_sql

#: Host and path of an address, without query and fragment.
HOST, PATH = "^[a-z]+://([^/?#]+)", "^[a-z]+://[^/?#]+([^?#]*)"
#: Words in a run that texts share.
RUN = 5
#: Spellings of Spark and of DuckDB.
SPELL = {
    "spark": {
        "words": lambda x: f"explode(split(lower({x}), '[^\\\\p{{{{L}}}}]+'))",
        "tags": lambda x: f"explode(regexp_extract_all({x}, '<([a-z0-9]+)', 1))",
        "key": lambda x: f"get_json_object({x}, '$.k')",
        "day": lambda x: f"date_format({x}, 'yyyy-MM-dd')",
        "parts": lambda x: f"explode(split(regexp_extract({x}, '{PATH}', 1), '/'))",
        "runs": lambda x: f"explode(CASE WHEN size({x}) >= {RUN} THEN array_distinct(transform(sequence(1, size({x}) - {RUN - 1}), p -> array_join(slice({x}, p, {RUN}), ' '))) END)",
        "blanks": lambda x: f"split(lower(trim({x})), ' +')",
        "str": "STRING",
    },
    "duckdb": {
        "words": lambda x: f"unnest(string_split_regex(lower({x}), '[^\\p{{{{L}}}}]+'))",
        "tags": lambda x: f"unnest(regexp_extract_all({x}, '<([a-z0-9]+)', 1))",
        "key": lambda x: f"json_extract_string({x}, '$.k')",
        "day": lambda x: f"strftime({x}, '%Y-%m-%d')",
        "parts": lambda x: f"unnest(string_split(regexp_extract({x}, '{PATH}', 1), '/'))",
        "runs": lambda x: f"unnest(list_transform(range(1, len({x}) - {RUN - 2}), lambda p: array_to_string({x}[p:p + {RUN - 1}], ' ')))",
        "blanks": lambda x: f"string_split_regex(lower(trim({x})), ' +')",
        "str": "VARCHAR",
    },
}
_LINES = "{lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey"


def _attrs(s: dict) -> str:
    text = lambda x: f"CAST({x} AS {s['str']})"
    values = [
        ("flag", "l_returnflag"), ("status", "l_linestatus"), ("quantity", text("CAST(floor(l_quantity / 5) AS INT)")), ("discount", text("CAST(round(l_discount * 100) AS INT)")),
        ("tax", text("CAST(round(l_tax * 100) AS INT)")), ("year", text("CAST(year(l_shipdate) AS INT)")), ("month", text("CAST(month(l_shipdate) AS INT)")),
    ]
    line = f"concat({text('l_orderkey')}, '-', {text('l_linenumber')})"
    return " UNION ".join(f"SELECT {line} AS t, concat('{n}=', {v}) AS i FROM {{lineitem}} WHERE {v} IS NOT NULL" for n, v in values)


#: Views made of others by leaving out frequent items.
WITHOUT_FREQUENT = {"customer_brandtype_rare": "customer_brandtype"}
#: Views of which few rows repeat: they are dealt out by transaction, where what repeats is dropped and what is grouped by transaction isn't shuffled again.
BY_TRANSACTION = ("run_texts",)


def sql(view: str, dialect: str = "spark") -> str:
    s = SPELL[dialect]
    text = lambda x: f"CAST({x} AS {s['str']})"
    parts = f"{_LINES} JOIN {{part}} p ON l.l_partkey = p.p_partkey"
    views = {
        "order_parts": "SELECT l_orderkey AS t, l_partkey AS i FROM {lineitem}",
        "order_suppliers": "SELECT l_orderkey AS t, l_suppkey AS i FROM {lineitem}",
        "customer_parts": f"SELECT o_custkey AS t, l_partkey AS i FROM {_LINES}",
        "customer_suppliers": f"SELECT o_custkey AS t, l_suppkey AS i FROM {_LINES}",
        "customer_brandtype": f"SELECT o_custkey AS t, concat(p_brand, '/', p_type) AS i FROM {parts}",
        "customer_brand": f"SELECT o_custkey AS t, p_brand AS i FROM {parts}",
        "line_attrs": _attrs(s),
        "user_keys": f"SELECT user_id AS t, concat(event_type, ':', {s['key']('props')}) AS i FROM {{events}} WHERE {s['key']('props')} IS NOT NULL",
        "user_day_events": f"SELECT concat({text('user_id')}, '@', {s['day']('ts')}) AS t, concat(event_type, ':', {text('CAST(floor(CAST(' + s['key']('props') + ' AS INT) / 10) AS INT)')}) AS i FROM {{events}} WHERE {s['key']('props')} IS NOT NULL",
        "doc_words": f"SELECT t, i FROM (SELECT doc_id AS t, {s['words']('text')} AS i FROM {{documents}}) x WHERE i <> ''",
        "word_docs": f"SELECT t, i FROM (SELECT {s['words']('text')} AS t, doc_id AS i FROM {{documents}}) x WHERE t <> ''",
        "supplier_parts": "SELECT l_suppkey AS t, l_partkey AS i FROM {lineitem}",
        "page_tags": f"SELECT page_id AS t, {s['tags']('html')} AS i FROM {{pages}}",
        "host_parts": f"SELECT t, i FROM (SELECT regexp_extract(url, '{HOST}', 1) AS t, {s['parts']('url')} AS i FROM {{pages}}) x WHERE t <> '' AND i <> ''",
        "source_words": f"SELECT t, i FROM (SELECT concat(coalesce(lang, '?'), '/', source) AS t, {s['words']('text')} AS i FROM {{documents}} WHERE source IS NOT NULL) x WHERE i <> ''",
        "word_sources": f"SELECT t, i FROM (SELECT {s['words']('text')} AS t, concat(coalesce(lang, '?'), '/', source) AS i FROM {{documents}} WHERE source IS NOT NULL) x WHERE t <> ''",
        "run_texts": (
            f"SELECT {s['runs']('w')} AS t, i FROM (SELECT concat('document ', {text('doc_id')}) AS i, {s['blanks']('text')} AS w FROM {{documents}}"
            f" UNION ALL SELECT concat('item ', {text('item_id')}), {s['blanks']('text')} FROM {{benchmark}}) x"
        ),
        "conv_words": f"SELECT t, i FROM (SELECT conv_id AS t, {s['words']('text')} AS i FROM {{conversations}}) x WHERE i <> ''",
    }
    if view in WITHOUT_FREQUENT:
        # the tenth of the items that occur most often left out
        of = sql(WITHOUT_FREQUENT[view], dialect)
        ranked = f"SELECT i, row_number() OVER (ORDER BY count(*) DESC, i) AS place, count(*) OVER () AS n FROM ({of}) x GROUP BY i"
        return f"SELECT b.t, b.i FROM ({of}) b JOIN ({ranked}) r ON b.i = r.i WHERE r.place > 0.1 * r.n"
    rows = f"FROM ({views[view]}) v WHERE t IS NOT NULL AND i IS NOT NULL"
    if dialect == "spark" and view in BY_TRANSACTION:
        return f"SELECT DISTINCT t, i FROM (SELECT t, i {rows} DISTRIBUTE BY t) d"
    return f"SELECT DISTINCT t, i {rows}"


VIEWS = (
    "order_parts order_suppliers customer_parts customer_suppliers customer_brandtype customer_brand line_attrs user_keys user_day_events doc_words word_docs supplier_parts page_tags conv_words customer_brandtype_rare host_parts run_texts source_words word_sources"
).split()
#: Thresholds of the cost table, for the cosine.
DELTAS = {
    "order_parts": 0.5, "order_suppliers": 0.5, "customer_parts": 0.5, "customer_suppliers": 0.5, "customer_brandtype": 0.3, "customer_brand": 0.7, "line_attrs": 0.5,
    "user_keys": 0.5, "user_day_events": 0.5, "word_docs": 0.5, "supplier_parts": 0.5, "page_tags": 0.5, "conv_words": 0.5, "customer_brandtype_rare": 0.3, "host_parts": 0.5, "run_texts": 0.5, "word_sources": 0.5,
}


def baskets(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    """A view as distinct (t, i) rows without nulls."""
    return run_sql(spark, sf_dir, sql(view))


def duck(text: str) -> str:
    """A marked query with the plain table names that DuckDB knows."""
    for name in NAMES:
        text = text.replace("{" + name + "}", name)
    return text.replace("{{", "{").replace("}}", "}")


def duck_view(view: str) -> str:
    return duck(sql(view, "duckdb"))
