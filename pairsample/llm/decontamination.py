"""Benchmark decontamination by containment search, with DataFrame functions only.

Every benchmark item is the set of its shingles (runs of ``k`` words; all its words where it has fewer). An item's
MinHash sketch is its smallest shingle hashes, and its size sets how many: a document that holds the share
``threshold`` of an item misses at most ``size - ceil(threshold * size)`` shingles, so one more than that number of
smallest hashes can't all be missing. Items are partitioned by their sizes: those of fewer than ``k`` words by their number of words, each such
part with its own largest sketch hash, up to which a document's shingles of that length are probed; a document of fewer shingles than an item's size
class needs isn't its candidate. Candidates are verified by counting the item's shingles, as
text, in the document. Documents are never cut, and no member of a group is paired with another: only sketches are joined.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch

NO_ID = -(2**63)


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text.cast("string")), r"[^\p{L}\p{N}]+"), "")


def shingles(words: str, k: int) -> Column:
    """Runs of k words; none where there are fewer words."""
    return F.expr(f"CASE WHEN size({words}) >= {k} THEN transform(sequence(1, size({words}) - {k - 1}), i -> slice({words}, i, {k})) ELSE array() END")


def hashes(words: str, k: int, upto: int) -> Column:
    return F.expr(
        f"CASE WHEN size({words}) >= {k} THEN filter(transform(sequence(1, size({words}) - {k - 1}), i -> xxhash64(slice({words}, i, {k}))), h -> h <= {upto}L) ELSE array() END"
    )


def sketch(benchmark: DataFrame, item_col: str, text_col: str, k: int, threshold: float) -> tuple[DataFrame, DataFrame]:
    """(item, shingle, n, k) of all shingles, and (item, k, need, h) of the sketches."""
    cut = benchmark.select(F.col(item_col).alias("item"), words_of(F.col(text_col)).alias("w")).where("size(w) > 0")
    cut = cut.withColumn("k", F.least(F.size("w"), F.lit(k)))
    runs = F.expr("transform(sequence(1, size(w) - k + 1), i -> slice(w, i, k))")
    full = cut.select("item", "k", F.explode(runs).alias("shingle")).distinct()
    sizes = full.groupBy("item").agg(F.count("*").alias("n"))
    need = F.ceil(F.col("n") * threshold - 1e-9).cast("int")
    ranked = full.select("item", "k", F.xxhash64("shingle").alias("h")).groupBy("item", "k").agg(F.array_sort(F.collect_set("h")).alias("hs"))
    lists = ranked.join(sizes, "item").select("item", "k", "n", need.alias("need"), F.expr(f"slice(hs, 1, n - ceil(n * {threshold} - 1e-9) + 1)").alias("hs"))
    small = lists.select("item", "k", "need", F.explode("hs").alias("h"))
    return full.join(sizes, "item"), small


def find_leaks(
    docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", k: int = 5, threshold: float = 0.8, broadcast_rows: int = 500_000,
) -> DataFrame:
    """Documents that hold at least ``threshold`` of the shingles of a benchmark item.

    Returns (doc_id, item_id, n_shingles, n_found, containment), one row per document id and item. Words are runs of
    letters and digits in lower case. A null or wordless item is never found; a null text holds nothing; a null document id is
    reported as null; rows that repeat an id count once, by the text that holds most. Empty tables give an empty one.
    ``broadcast_rows`` is the largest sketch, shingle or candidate table that is broadcast, counted first; beyond it all joins shuffle.
    """
    scratch = Scratch(docs.sparkSession, "leaks")
    full, small = sketch(benchmark, item_col, item_text_col, k, threshold)
    full, small = scratch.write(full), scratch.write(small)
    # of each length of shingles, at most k of them, the largest hash of a sketch
    upto = {r["k"]: r["top"] for r in small.groupBy("k").agg(F.max("h").alias("top")).collect()} or {k: -(2**63) + 1}
    lengths = sorted(upto)

    def bounded(df: DataFrame) -> DataFrame:
        return F.broadcast(df) if df.limit(broadcast_rows + 1).count() <= broadcast_rows else df

    keyed = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("d"), F.xxhash64(F.col(text_col).cast("string")).alias("th"), words_of(F.col(text_col)).alias("w"))
    probes = keyed.select("d", "th", F.size("w").alias("size"), F.explode(F.concat(*[hashes("w", n, upto[n]) for n in lengths])).alias("h"))
    candidates = scratch.write(
        probes.join(bounded(small), "h").where("size >= need").select("d", "th", "item").distinct()
    )
    wanted = candidates.groupBy("d", "th").agg(F.collect_set("item").alias("items"))
    held = (
        keyed.join(bounded(wanted), ["d", "th"])
        .select("d", "th", "items", F.explode(F.array_distinct(F.concat(*[shingles("w", n) for n in lengths]))).alias("shingle"))
        .join(bounded(full), "shingle")
        .where(F.array_contains("items", F.col("item")))
        .select("d", "th", "item", "n", "shingle").distinct()
    )
    counted = held.groupBy("d", "th", "item", "n").agg(F.count("*").alias("found")).where(F.col("found") >= F.col("n") * threshold - 1e-9)
    best = counted.groupBy("d", "item", "n").agg(F.max("found").alias("found"))
    return best.select(
        F.when(F.col("d") != NO_ID, F.col("d")).alias(id_col), F.col("item").alias(item_col),
        F.col("n").alias("n_shingles"), F.col("found").alias("n_found"), F.round(F.col("found") / F.col("n"), 6).alias("containment"),
    )


def remove_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of ``docs`` whose id is in no leak, with all their columns. Rows without an id go if any such row leaks."""
    leaking = find_leaks(docs, benchmark, id_col, **options).select(F.coalesce(F.col(id_col), F.lit(NO_ID)).alias("_leaking")).distinct()
    return docs.join(leaking, F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)) == F.col("_leaking"), "left_anti")


ORACLE = r"""
WITH iw AS (SELECT item_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM benchmark),
ik AS (SELECT item_id, w, least(len(w), 5) AS k FROM iw WHERE len(w) > 0),
i AS (SELECT DISTINCT item_id, unnest(list_transform(range(1, len(w) - k + 2), lambda s: w[s:s + k - 1])) AS g FROM ik),
n AS (SELECT item_id, count(*) AS n FROM i GROUP BY 1),
dw AS (SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM documents),
kk AS (SELECT DISTINCT k FROM ik),
d AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, len(w) - k + 2), lambda s: w[s:s + k - 1])) AS g FROM dw, kk WHERE len(w) >= k),
f AS (SELECT doc_id, item_id, count(*) AS f FROM d JOIN i USING (g) GROUP BY 1, 2)
SELECT doc_id, item_id, n::BIGINT AS n_shingles, f::BIGINT AS n_found, round(f / n, 6) AS containment
FROM f JOIN n USING (item_id) WHERE f >= n * 0.8::DOUBLE - 1e-9
"""
