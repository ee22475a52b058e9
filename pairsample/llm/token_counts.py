"""Token counts by a map-side two-tier lookup of pre-token lengths.

A first pass keeps, per task, a mergeable summary of the heaviest pre-tokens (bounded counters, merged
in levels of a fixed fan-in), so that no pre-token is shuffled. The heaviest of the corpus are encoded once on the
driver and broadcast as a table of bounded size. A second pass cuts every text into pre-tokens, adds up known
lengths and encodes the rest through a bounded cache of the worker. The table and the cache only save time: every
length comes from the tokenizer, whose pieces never reach across the cuts (``cut_is_safe`` checks it).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import kept_by_worker

#: Spaces with the word that follows them; a line feed is a token of its own bytes and ends a word.
UNITS = re.compile(r"\n| *[^ \n]+| +")
SPACE = "▁"
FAN_IN = 64
LONGEST_KEPT = 48


def load(model_path: str | None):
    import public_tokenizers
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=model_path or public_tokenizers.path("piece_bpe_32k.model"))


def cut_is_safe(model) -> bool:
    """No piece holds a space after another character or a line feed, so no merge crosses a cut of UNITS."""
    pieces = (model.id_to_piece(i) for i in range(model.get_piece_size()))
    return not any(re.search(f"[^{SPACE}]{SPACE}|\n", p) for p in pieces)


def units(text: str) -> list[str]:
    return UNITS.findall(" " + text.replace(SPACE, " ")) if text else []


def unit_length(model, unit: str) -> int:
    """Tokens of a unit inside a text: the line feed put before it costs itself and the leading space mark."""
    return 1 if unit == "\n" else len(model.encode("\n" + unit)) - 2


def shrink(counts: Counter, size: int) -> Counter:
    """At most ``size`` counters; each loses the count of the first one left out, which bounds the error."""
    if len(counts) <= size:
        return counts
    top = counts.most_common(size + 1)
    floor = top[-1][1]
    return Counter({w: c - floor for w, c in top[:-1] if c > floor})


class Lengths(dict):
    """Pre-token lengths: the broadcast table, and below it what this worker has met, up to ``room`` entries."""

    def __init__(self, table: dict[str, int], model, room: int) -> None:
        super().__init__(table)
        self.table, self.model, self.room = table, model, room

    def __missing__(self, unit: str) -> int:
        n = unit_length(self.model, unit)
        if len(unit) <= LONGEST_KEPT:
            if len(self) >= len(self.table) + self.room:
                self.clear()
                self.update(self.table)
            self[unit] = n
        return n


def worker_lengths(table, model_path: str | None, room: int) -> Lengths:
    """One cache for a worker process; a new broadcast table replaces it."""
    return kept_by_worker(("token_counts", id(table), len(table), model_path, room), lambda: Lengths(table, load(model_path), room))


def frequent_units(docs: DataFrame, text_col: str, size: int) -> list[str]:
    """The heaviest pre-tokens over all texts, at most ``size``."""

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()
        for batch in batches:
            for text in batch.column(0):
                counts.update(units(text.as_py() or ""))
                if len(counts) > 8 * size:
                    counts = shrink(counts, size)
        counts = shrink(counts, size)
        yield pa.RecordBatch.from_pydict(
            {"at": [TaskContext.get().partitionId()], "unit": [list(counts.keys())], "n": [list(counts.values())]},
            schema=pa.schema([("at", pa.int64()), ("unit", pa.list_(pa.string())), ("n", pa.list_(pa.int64()))]),
        )

    def merge(frame):
        counts: Counter = Counter()
        for words, ns in zip(frame["unit"], frame["n"], strict=True):
            counts.update(dict(zip(words, map(int, ns), strict=True)))
            counts = shrink(counts, 4 * size)
        counts = shrink(counts, size)
        import pandas as pd

        return pd.DataFrame({"at": [int(frame["at"].iloc[0])], "unit": [list(counts.keys())], "n": [list(counts.values())]})

    schema = "at long, unit array<string>, n array<long>"
    summaries = docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(summarise, schema)
    left = docs.rdd.getNumPartitions()
    while left > 1:
        left = -(-left // FAN_IN)
        summaries = summaries.withColumn("at", F.floor(F.col("at") / FAN_IN)).groupBy("at").applyInPandas(merge, schema)
    rows = summaries.collect()  # one row of bounded size
    total: Counter = Counter()
    for row in rows:
        total.update(dict(zip(row["unit"], row["n"], strict=True)))
    return [w for w, _ in total.most_common(size)]


def count_tokens(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model_path: str | None = None,
    limit: int = 4096, table_size: int = 8192, cache_size: int = 600_000,
) -> DataFrame:
    """Tokens of every whole text as the sentencepiece model gives them, without begin or end tokens.

    Returns (id_col, n_bytes, n_tokens, over_limit). A null text counts as empty (0 bytes, 0 tokens); a null id is
    kept. Repeated rows give repeated results, an empty table an empty one. Other columns of ``docs`` are not read.
    ``table_size`` bounds the broadcast table, ``cache_size`` the entries of a worker's cache.
    """
    spark = docs.sparkSession
    model = load(model_path)
    if not cut_is_safe(model):
        raise ValueError("pieces of this model reach across words; its texts can't be cut")
    table = spark.sparkContext.broadcast({w: unit_length(model, w) for w in frequent_units(docs, text_col, table_size) if len(w) <= LONGEST_KEPT})

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = worker_lengths(table.value, model_path, cache_size)
        for batch in batches:
            n_bytes, n_tokens = [], []
            for text in batch.column(1):
                text = text.as_py() or ""
                n_bytes.append(len(text.encode()))
                n_tokens.append(sum(map(known.__getitem__, units(text))))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64())], names=["key", "n_bytes", "n_tokens"]
            )

    source = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("string").alias("text"))
    counted = source.mapInArrow(count, "key long, n_bytes long, n_tokens long")
    return counted.select(F.col("key").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
