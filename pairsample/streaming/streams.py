"""Baskets from a stream of events, and one-pass sampling that agrees with the batch.

As weights fall while supports grow, what an early look at the supports admits contains what the final ones admit: candidates are kept with their draw, and
the final test is applied when they are read. That doesn't hold for lift, whose weight grows with the number of transactions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, dbl, get
from pairsample.operators.sampling import count_pairs, pack, prefix_pairs


def item() -> Column:
    """The item of an event: its type and the tens of its key."""
    return F.concat_ws(":", F.col("event_type"), F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string"))


def window_baskets(events: DataFrame, length: str, slide: str | None = None, session_gap: str | None = None, watermark: str | None = None) -> DataFrame:
    """(user_id, start, items, n): the distinct items of each user in each window; works on streams and on tables alike."""
    rows = events.where("user_id IS NOT NULL AND ts IS NOT NULL").select("user_id", F.col("ts").cast("timestamp").alias("ts"), item().alias("item"))
    rows = rows.withWatermark("ts", watermark) if watermark else rows
    span = F.session_window("ts", session_gap) if session_gap else F.window("ts", length, slide) if slide else F.window("ts", length)
    grouped = rows.groupBy("user_id", span.alias("w")).agg(F.collect_set("item").alias("items"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.array_sort("items").alias("items"), F.size("items").alias("n"))


def without_repeats(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each event once, however often it is sent within the watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def running_supports(events: DataFrame, exact: bool = False) -> DataFrame:
    """Item counts (i, c) over all baskets so far (user and day), for update mode: approximate distinct counts keep the state bounded.

    ``exact`` counts distinct baskets, which only a table can.
    """
    rows = events.select(item().alias("i"), F.xxhash64("user_id", F.to_date("ts")).alias("t")).where("i IS NOT NULL")
    return rows.groupBy("i").agg((F.count_distinct("t") if exact else F.approx_count_distinct("t", 0.01)).alias("c"))


def admit(rows: DataFrame, supports: DataFrame, measure: str | Measure, mu: float, delta: float, seed: int = 42) -> DataFrame:
    """Candidates (t, i, j, r) of closed baskets (t, i) under the supports (i, c) known at the time.

    An item of unknown support counts as one that occurs once, at which its weight is largest, so nothing that later supports take is lost.
    Partners are found by search along the order of the supports known; the names of a candidate are in their own order, as supports may still change.
    """
    of = get(measure)
    if of.uses_m:
        raise ValueError("the weight of this measure grows with the stream; sample it in two passes")
    known = rows.join(supports, "i", "left").select("t", "i", F.coalesce("c", F.lit(1)).cast("long").alias("c"), F.lit(1).cast("long").alias("m"))
    pairs = prefix_pairs(pack(known.withColumn("r", F.expr(draws.draw_sql(seed)))), of, mu, delta)
    return pairs.select("t", F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), F.expr(draws.draw_sql(seed)).alias("r"))


PAIRS_SCHEMA = "t string, i string, j string, r double"


def pairs_as_they_come(events: DataFrame, watermark: str = "1 hour", seed: int = 42) -> DataFrame:
    """(t, i, j, r) of a stream: each pair of items of a user's day once, as soon as its second item has come, with the draw of the basket.

    The state of a basket holds its items and goes when the watermark has passed the day's end. ``t`` is ``user@day``; i < j by name.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        import hashlib

        import pandas as pd

        name = f"{key[0]}@{key[1]}"
        if state.hasTimedOut:
            state.remove()
            return
        seen = list(state.get[0]) if state.exists else []
        known = set(seen)
        out = []
        for frame in frames:
            for x in frame["item"]:
                if x not in known:
                    out += [(min(x, y), max(x, y)) for y in seen]
                    known.add(x)
                    seen.append(x)
        state.update((seen,))
        end = int(pd.Timestamp(key[1], tz="UTC").timestamp() * 1000) + 86_400_000
        if end > state.getCurrentWatermarkMs():
            state.setTimeoutTimestamp(end)
        else:
            state.remove()
        r = int(hashlib.md5(f"{seed}:{name}".encode()).hexdigest()[:8], 16) / 4294967296.0
        yield pd.DataFrame({"t": name, "i": [a for a, _ in out], "j": [b for _, b in out], "r": r})

    rows = events.where("user_id IS NOT NULL AND ts IS NOT NULL").select(F.col("user_id").cast("string").alias("user"), F.date_format("ts", "yyyy-MM-dd").alias("day"), F.col("ts").cast("timestamp").alias("ts"), item().alias("item")).where("item IS NOT NULL")
    return rows.withWatermark("ts", watermark).groupBy("user", "day").applyInPandasWithState(step, PAIRS_SCHEMA, "items array<string>", "append", GroupStateTimeout.EventTimeTimeout)


def with_items(events: DataFrame, table: DataFrame, item_col: str = "i") -> DataFrame:
    """Events (streamed or not) with the columns of a table of items, which is read anew in every batch; events of unknown items keep nulls."""
    return events.withColumn(item_col, item()).join(table, item_col, "left")


def thin(candidates: DataFrame, supports: DataFrame, measure: str | Measure, mu: float, delta: float) -> DataFrame:
    """The sample (i, j, k, ci, cj) that the batch would draw with these supports, from candidates admitted under smaller ones."""
    of = get(measure)
    first = supports.select(F.col("i"), F.col("c").alias("a"))
    second = supports.select(F.col("i").alias("j"), F.col("c").alias("b"))
    rows = candidates.join(first, "i").join(second, "j")
    ordered = rows.select(
        "r", F.when(F.expr("a < b OR (a = b AND i < j)"), F.struct("i", "j", F.col("a").alias("ci"), F.col("b").alias("cj"))).otherwise(F.struct(F.col("j").alias("i"), F.col("i").alias("j"), F.col("b").alias("ci"), F.col("a").alias("cj"))).alias("p")
    ).select("r", "p.*")
    return count_pairs(ordered.where(f"{of.weight_sql(delta)} * {dbl(mu)} > r").select("i", "j", "ci", "cj"))
