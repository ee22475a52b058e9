"""Language-model scores by deleted interpolation of bigram, unigram and uniform estimates.

P(v | u) = a c(u,v)/c(u) + b c(v)/N + g /(V+1). The weights a, b, g depend on the bucket of c(u) (its binary logarithm) and
are learned by expectation-maximisation on the counts of a held-out part of the training texts, the estimates then coming from the rest.

Counts are gathered by key, not by token. A block of texts sends each key it holds (a word or a pair of words, hashed to 64 bits)
once, with its counts in the block: sorted keys are cut by range and sent as byte planes of their differences. A shard adds up
what all blocks sent and answers each block in the order it asked. Blocks then meet their answers and score their texts.
Nothing depends on how often a word or pair occurs, so no key is hot.

No sender has more than FAN messages to send. Where there are more shards, blocks reach them over levels: at each level a node adds up what
about as many senders know of its range of keys and sends that on to the narrower ranges of the next, and answers come back
the same way. A node holds about as much as a block, and messages grow with the input times the number of levels, not with its square.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch

#: Not a word, as words hold no white space: ends a text, and stands before its first word.
END = b"\n"
BLOCK_CHARS = 9_000_000
SHARD_CHARS = 6_000_000
#: Most ranges that a block or node sends to: a message then still holds some hundred keys, so that its own cost stays small beside theirs.
FAN = 2048
#: Steps of probability per octave in the table that expectation-maximisation reads.
FINE = 4
BUCKETS = 64


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def pack(values: np.ndarray) -> bytes:
    """Unsigned integers as byte planes, the highest that are all zero left out."""
    planes = values.astype("<u8").view(np.uint8).reshape(-1, 8).T
    used = 8
    while used > 1 and not planes[used - 1].any():
        used -= 1
    return np.ascontiguousarray(planes[:used]).tobytes()


def unpack(raw: bytes, n: int) -> np.ndarray:
    if not n:
        return np.zeros(0, np.uint64)
    planes = np.frombuffer(raw, np.uint8).reshape(-1, n)
    full = np.zeros((n, 8), np.uint8)
    full[:, : len(planes)] = planes.T
    return full.view("<u8").ravel()


def pack_sorted(keys: np.ndarray) -> bytes:
    return pack(np.diff(keys, prepend=np.uint64(0)))


def unpack_sorted(raw: bytes, n: int) -> np.ndarray:
    return np.cumsum(unpack(raw, n), dtype=np.uint64)


class Block:
    """Texts as numbers: each token's word and pair as positions in the block's sorted keys."""

    def __init__(self, texts: list[bytes]) -> None:
        number: dict[bytes, int] = defaultdict(count().__next__)
        end = number[END]
        parts = [np.array([*map(number.__getitem__, t.lower().split()), end], np.int64) for t in texts]
        self.sizes = np.array([len(p) for p in parts], np.int64)
        token = np.concatenate(parts) if parts else np.zeros(0, np.int64)
        context = np.concatenate([[end], token[:-1]]) if len(token) else token
        word = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in number), np.uint64, len(number))
        pair, at = np.unique(context * len(number) + token, return_inverse=True)
        with np.errstate(over="ignore"):
            both = mix(word[pair // len(number)] * np.uint64(0x9E3779B97F4A7C15) + mix(word[pair % len(number)]))
        # the lowest bit tells words from pairs
        word, both = word | np.uint64(1), both & ~np.uint64(1)
        self.keys, place = np.unique(np.concatenate([word, both]), return_inverse=True)
        self.token, self.context = place[token], place[context]
        self.pair = place[len(number) + at]
        self.starts = np.cumsum(self.sizes) - self.sizes

    def counts(self, chosen: np.ndarray) -> np.ndarray:
        """How often each key occurs in the chosen texts."""
        inside = np.repeat(chosen, self.sizes)
        n = len(self.keys)
        return np.bincount(self.token[inside], minlength=n) + np.bincount(self.pair[inside], minlength=n)


def levels_of(shards: int) -> tuple[int, int]:
    """Levels of nodes and ranges a sender sends to, so that the last level has at least so many ranges."""
    levels = 1
    while FAN**levels < shards:
        levels += 1
    fan = 1
    while fan**levels < shards:
        fan += 1
    return levels, fan


def cut(keys: np.ndarray, part: int, parts: int, fan: int) -> np.ndarray:
    """Where sorted keys of one of ``parts`` equal ranges pass into each of its ``fan`` equal ranges."""
    bounds = np.array([(k << 64) // (parts * fan) for k in range(part * fan + 1, (part + 1) * fan)], np.uint64)
    return np.concatenate([[0], np.searchsorted(keys, bounds), [len(keys)]]).astype(np.int64)


ASK = pa.schema([("team", pa.int64()), ("shard", pa.int64()), ("block", pa.int64()), ("fold", pa.bool_()), ("n", pa.int32()), ("keys", pa.binary()), ("train", pa.binary()), ("held", pa.binary())])
ANSWER = pa.schema([("block", pa.int64()), ("fold", pa.bool_()), ("shard", pa.int64()), ("n", pa.int32()), ("check", pa.int64()), ("counts", pa.binary()), ("held", pa.binary()), ("types", pa.int64()), ("tokens", pa.int64())])
TEXTS = pa.schema([("block", pa.int64()), ("key", pa.int64()), ("train", pa.bool_()), ("held", pa.bool_()), ("text", pa.binary())])


def tagged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with the number of their block: a task's rows in their order, cut whenever a block has BLOCK_CHARS."""
    at, held = TaskContext.get().partitionId() << 24, 0
    for batch in batches:
        text = pa.array([x.as_py() or b"" for x in batch.column(3)], pa.binary())
        numbers = []
        for x in text:
            if held >= BLOCK_CHARS:
                at, held = at + 1, 0
            held += len(x.as_py())
            numbers.append(at)
        yield pa.RecordBatch.from_arrays([pa.array(numbers, pa.int64()), *batch.columns[:3], text], schema=TEXTS)


def messages(keys: np.ndarray, part: int, parts: int, fan: int, totals: list[np.ndarray], team: int, block: int, fold: bool) -> pa.RecordBatch:
    """Keys of a range and their counts, one row for each of its ``fan`` ranges that holds any."""
    cuts = cut(keys, part, parts, fan)
    columns: list[list] = [[] for _ in ASK]
    for k, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
        if a < b:
            blobs = [pack(c[a:b]) for c in totals] or [None, None]
            for column, value in zip(columns, (team, part * fan + k, block, fold, b - a, pack_sorted(keys[a:b]), *blobs), strict=True):
                column.append(value)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, ASK, strict=True)], schema=ASK)


def asked(block: int, rows: list[tuple[bool, bool, bytes]], fan: int, teams: int) -> Iterator[pa.RecordBatch]:
    """What a block asks for: all its keys with their counts, and once more the keys of its held-out texts."""
    train, held = np.array([r[0] for r in rows], bool), np.array([r[1] for r in rows], bool)
    team = xxhash.xxh3_64_intdigest(block.to_bytes(8, "little")) % teams
    for fold in (False, True):
        chosen = [r[2] for r in rows if r[1] or not fold]
        if chosen:
            own = Block(chosen)
            yield messages(own.keys, 0, 1, fan, [] if fold else [own.counts(train), own.counts(held)], team, block, fold)


def ask(fan: int, teams: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, rows = None, []
        for batch in tagged(batches):
            for block, train, held, text in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3, 4)), strict=True):
                if now is not None and block != now:
                    yield from asked(now, rows, fan, teams)
                    rows = []
                now = block
                rows.append((train, held, text))
        if rows:
            yield from asked(now, rows, fan, teams)

    return run


class Node:
    """What several senders asked about one range: the distinct keys, their summed counts and the place of each sender's keys."""

    def __init__(self, asks: pa.Table) -> None:
        self.rows = asks.to_pylist()
        self.asked = [unpack_sorted(r["keys"], r["n"]) for r in self.rows]
        self.keys, place = np.unique(np.concatenate(self.asked), return_inverse=True)
        cuts = np.cumsum([0] + [len(k) for k in self.asked])
        self.places = [place[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        self.train, self.held = np.zeros(len(self.keys), np.int64), np.zeros(len(self.keys), np.int64)
        for r, at in zip(self.rows, self.places, strict=True):
            if not r["fold"]:
                self.train[at] += unpack(r["train"], r["n"]).astype(np.int64)
                self.held[at] += unpack(r["held"], r["n"]).astype(np.int64)

    def answers(self, train: np.ndarray, held: np.ndarray, to_blocks: bool) -> list[dict]:
        """Each sender's counts in the order it asked. Blocks get those of all training texts or, for a fold, of those not held out; nodes get both."""
        return [
            {"block": r["block"], "fold": r["fold"], "shard": r["shard"], "n": r["n"], "check": int(np.bitwise_xor.reduce(k).astype(np.int64)),
             "counts": pack(((train - held) if r["fold"] else train)[at]), "held": None if to_blocks else pack(held[at])}
            for r, k, at in zip(self.rows, self.asked, self.places, strict=True)
        ]


def sent_on(parts: int, fan: int, teams: int):
    """A node of a level with ``parts`` ranges sends its sums to the next level."""

    def run(key: tuple[pa.Scalar, ...], asks: pa.Table) -> pa.Table:
        node, (team, shard) = Node(asks), (k.as_py() for k in key)
        return pa.Table.from_batches([messages(node.keys, shard, parts, fan, [node.train, node.held], team % teams, team, False)])

    return run


def answered(to_blocks: bool):
    """A shard's answers, and how many words and tokens it has counted."""

    def run(key: tuple[pa.Scalar, ...], asks: pa.Table) -> pa.Table:
        node = Node(asks)
        word = (node.keys & np.uint64(1)).astype(bool)
        train, left = node.train[word], (node.train - node.held)[word]
        sums = [
            {"block": -1, "fold": fold, "shard": key[1].as_py(), "n": 0, "types": int((c > 0).sum()), "tokens": int(c.sum())}
            for fold, c in ((False, train), (True, left))
        ]
        return pa.Table.from_pylist(node.answers(node.train, node.held, to_blocks) + sums, schema=ANSWER)

    return run


def passed_back(to_blocks: bool):
    """What a node was answered, for each of its senders."""

    def run(key, asks: pa.Table, answers: pa.Table) -> pa.Table:
        node, got = Node(asks), sorted(answers.to_pylist(), key=lambda r: r["shard"])
        if sum(r["n"] for r in got) != len(node.keys):
            raise RuntimeError("a node lacks some of its answers")
        train, held = (np.concatenate([unpack(r[c], r["n"]) for r in got]).astype(np.int64) for c in ("counts", "held"))
        return pa.Table.from_pylist(node.answers(train, held, to_blocks), schema=ANSWER)

    return run


def met(texts: pa.Table, answers: pa.Table) -> tuple[Block, np.ndarray]:
    """A block and the count of each of its keys; an error where the answers aren't to its own questions."""
    own = Block([x or b"" for x in texts["text"].to_pylist()])
    got = sorted(answers.to_pylist(), key=lambda r: r["shard"])
    if sum(r["n"] for r in got) != len(own.keys) or np.bitwise_xor.reduce([np.int64(r["check"]) for r in got]) != np.bitwise_xor.reduce(own.keys).astype(np.int64):
        raise RuntimeError("the texts of a block changed between two readings; write the table first")
    return own, np.concatenate([unpack(r["counts"], r["n"]) for r in got]).astype(np.int64)


def bucket(context: np.ndarray) -> np.ndarray:
    return np.minimum(np.log2(context + 1.0).astype(np.int64), BUCKETS - 1)


def ratios(own: Block, counts: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each token: the count of its context, and its bigram and unigram estimates."""
    context = counts[own.context]
    return context, counts[own.pair] / np.maximum(context, 1), counts[own.token] / max(total, 1)


def level(p: np.ndarray) -> np.ndarray:
    """-1 for 0, else the place of p on a logarithmic scale."""
    return np.where(p > 0, np.round(-FINE * np.log2(np.where(p > 0, p, 1))), -1).astype(np.int64)


def fold_table(total: int):
    def run(key, texts: pa.Table, answers: pa.Table) -> pa.Table:
        own, counts = met(texts, answers)
        context, p2, p1 = ratios(own, counts, total)
        kinds, n = np.unique(np.stack([bucket(context), level(p2), level(p1)]), axis=1, return_counts=True)
        return pa.table({"b": kinds[0], "p2": kinds[1], "p1": kinds[2], "n": n.astype(np.int64)})

    return run


def learn_weights(b: np.ndarray, p2: np.ndarray, p1: np.ndarray, n: np.ndarray, uniform: float, rounds: int = 60) -> np.ndarray:
    """Mixture weights (bucket, [bigram, unigram, uniform]) by expectation-maximisation on counted held-out tokens."""
    weights = np.tile([0.5, 0.4, 0.1], (BUCKETS, 1))
    value = np.stack([np.where(p >= 0, 2.0 ** (-p / FINE), 0.0) for p in (p2, p1)] + [np.full(len(b), uniform)], axis=1)
    seen = np.bincount(b, n, BUCKETS)
    for _ in range(rounds):
        part = weights[b] * value
        part *= (n / part.sum(axis=1))[:, None]
        grown = np.stack([np.bincount(b, part[:, k], BUCKETS) for k in range(3)], axis=1)
        # half a count for each keeps every weight above zero, and a bucket without tokens as it was
        weights = np.where(seen[:, None] > 0, (grown + 0.5) / (seen + 1.5)[:, None], weights)
    return weights


def score_texts(
    docs: DataFrame, train: Column, id_col: str = "doc_id", text_col: str = "text", held_share: int = 10, stable: bool = False,
) -> DataFrame:
    """Scores of all whole texts under a model learned from the rows where ``train`` holds.

    Returns (id_col, n_tokens, n_known, train_tokens, base_score, score). Tokens are words of lower-cased A-Z text, then one end.
    base_score is the add-one unigram score, score the interpolated one, both sums of base-10 logarithms. A null text counts as
    empty (one token); a null ``train`` as false; null ids and repeated rows are kept and scored one by one. An empty table gives an empty
    one; without training rows every token has probability 1. About one in ``held_share`` training texts is held out for the weights.

    Blocks are read twice and must not change in between: that holds for a plain scan of files (``stable=True``); any other
    table is written to the shared folder first.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "language-model")
    rows = docs.select(
        F.col(id_col).cast("long").alias("key"), F.coalesce(train, F.lit(False)).alias("train"),
        (F.coalesce(train, F.lit(False)) & (F.pmod(F.xxhash64(F.lit("held"), F.col(id_col).cast("string")), F.lit(held_share)) == 0)).alias("held"),
        F.col(text_col).cast("string").cast("binary").alias("text"),
    )
    rows = rows if stable else scratch.write(rows)
    # the number of scan tasks follows the cores of the moment unless it is held
    cores, before = str(spark.sparkContext.defaultParallelism), spark.conf.get("spark.sql.files.minPartitionNum", None)
    spark.conf.set("spark.sql.files.minPartitionNum", before or cores)
    try:
        chars = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        shards = max(8, math.ceil(chars / SHARD_CHARS))
        levels, fan = levels_of(shards)
        teams = [fan ** (levels - k) for k in range(1, levels + 1)]
        ddl = {"ask": "team long, shard long, block long, fold boolean, n int, keys binary, train binary, held binary"}
        ddl["answer"] = "block long, fold boolean, shard long, n int, check long, counts binary, held binary, types long, tokens long"
        ddl["texts"] = "block long, key long, train boolean, held boolean, text binary"
        asks, below = rows.mapInArrow(ask(fan, teams[0]), ddl["ask"]), []
        for k in range(1, levels):
            # read again on the way back
            below.append(scratch.write(asks))
            asks = below[-1].groupBy("team", "shard").applyInArrow(sent_on(fan**k, fan, teams[k]), ddl["ask"])
        answers = scratch.write(asks.groupBy("team", "shard").applyInArrow(answered(not below), ddl["answer"]))
        sums = {r["fold"]: (r["types"], r["tokens"]) for r in answers.where("block = -1").groupBy("fold").agg(F.sum("types").alias("types"), F.sum("tokens").alias("tokens")).collect()}
        (types, tokens), (left_types, left_tokens) = sums.get(False, (0, 0)), sums.get(True, (0, 0))

        while below:
            asks = below.pop()
            back = answers.where("block >= 0").withColumns({"team": F.col("block"), "node": F.expr(f"shard div {fan}")})
            answers = scratch.write(asks.groupBy("team", "shard").cogroup(back.groupBy("team", "node")).applyInArrow(passed_back(not below), ddl["answer"]))
            scratch.drop(asks)

        texts = rows.mapInArrow(tagged, ddl["texts"])
        part = lambda fold: answers.where("block >= 0").where(F.col("fold") == fold).groupBy("block")
        seen = texts.where("held").groupBy("block").cogroup(part(True)).applyInArrow(fold_table(left_tokens), "b long, p2 long, p1 long, n long")
        table = seen.groupBy("b", "p2", "p1").agg(F.sum("n").alias("n")).toPandas()  # bounded by the steps of the scale
        weights = learn_weights(*(table[c].to_numpy(np.int64) for c in ("b", "p2", "p1", "n")), 1.0 / (left_types + 1))

        def score(key, texts: pa.Table, answers: pa.Table) -> pa.Table:
            own, counts = met(texts, answers)
            context, p2, p1 = ratios(own, counts, tokens)
            mine = counts[own.token]
            base = np.log10((mine + 1) / (tokens + types + 1))
            w = weights[bucket(context)]
            full = np.log10(w[:, 0] * p2 + w[:, 1] * p1 + w[:, 2] / (types + 1)) if tokens else np.zeros(len(mine))
            add = lambda x: np.add.reduceat(x, own.starts)
            return pa.table({"key": texts["key"], "n_tokens": own.sizes, "n_known": add((mine > 0).astype(np.int64)), "base_score": add(base), "score": add(full)})

        scored = texts.groupBy("block").cogroup(part(False)).applyInArrow(score, "key long, n_tokens long, n_known long, base_score double, score double")
        done = scratch.write(scored)
    finally:
        if before is None:
            spark.conf.unset("spark.sql.files.minPartitionNum")
    scratch.drop(answers)
    return done.select(F.col("key").alias(id_col), "n_tokens", "n_known", F.lit(tokens).cast("long").alias("train_tokens"), "base_score", "score")
