"""Byte-level BPE encoding and decoding by merge replay over blocks of the corpus.

The distinct pre-tokens of a block lie one after another in one array of symbols. An inverted index leads from each
rank to the positions where a pair of that rank stands; ranks are replayed from the smallest, and a merge touches
only the two neighbours of its position. Blocks are bounded, so memory is too, and nothing is shuffled: each task
replays the blocks of its own texts and keeps the encodings it has seen in a bounded cache.
"""

from __future__ import annotations

import base64
import heapq
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import kept_by_worker

BLOCK_CHARS = 1_320_000
REPLAY_BYTES = 1_000_000
#: Letters, numbers and white space among the characters up to U+024F: the classes of the pattern, for the faster standard matcher.
LETTER, NUMBER, WHITE = "A-Za-z\u00aa\u00b5\u00ba\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f", "0-9\u00b2\u00b3\u00b9\u00bc-\u00be", "\x09-\x0d\x20\x85\xa0"
BEYOND = re.compile("[^\x00-\u024f]")
LONGEST_KEPT = 64


def read_ranks(path: str | None) -> dict[bytes, int]:
    import public_tokenizers

    with open(path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, filter(bytes.strip, lines))}


def token_bytes(path: str | None) -> dict[int, bytes]:
    return {i: t for t, i in read_ranks(path).items()}


class Vocabulary:
    """Ranks of byte strings, and every pair of tokens whose joint bytes are a token."""

    def __init__(self, path: str | None = None) -> None:
        import public_tokenizers
        import regex

        self.pattern = regex.compile(public_tokenizers.PATTERN)
        classes = ((r" ?[^\s\p{L}\p{N}]+", f" ?[^{WHITE}{LETTER}{NUMBER}]+"), (r"\p{L}", f"[{LETTER}]"), (r"\p{N}", f"[{NUMBER}]"), (r"\S", f"[^{WHITE}]"), (r"\s", f"[{WHITE}]"))
        near = public_tokenizers.PATTERN
        for general, listed in classes:
            near = near.replace(general, listed)
        self.near = re.compile(near)
        ranks = read_ranks(path)
        self.first_array = np.array([ranks[bytes([b])] for b in range(256)], np.int64)
        self.whole = ranks
        self.width = max(ranks.values()) + 1
        pairs = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    pairs[left * (self.width + 1) + right] = rank
        # open addressing: a power of two of slots, at most an eighth of them full, probed in steps of one
        self.mask = (1 << (8 * max(1, len(pairs))).bit_length()) - 1
        self.slot_key = np.full(self.mask + 1, -1, np.int64)
        self.slot_rank = np.full(self.mask + 1, -1, np.int32)
        self.probes = 1
        for key, rank in pairs.items():
            slot, probe = self._slot(key), 1
            while self.slot_key[slot] >= 0:
                slot, probe = (slot + 1) & self.mask, probe + 1
            self.slot_key[slot], self.slot_rank[slot] = key, rank
            self.probes = max(self.probes, probe)

    def _slot(self, key):
        return (key ^ (key >> 13)) * 40503 & self.mask

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair of tokens, -1 where the two don't merge."""
        key = left.astype(np.int64) * (self.width + 1) + right
        slot = self._slot(key)
        rank = np.where(self.slot_key[slot] == key, self.slot_rank[slot], -1)
        for _ in range(self.probes - 1):
            open_ = np.flatnonzero((rank < 0) & (self.slot_key[slot] >= 0))
            if not len(open_):
                break
            slot = (slot + 1) & self.mask
            rank[open_] = np.where(self.slot_key[slot[open_]] == key[open_], self.slot_rank[slot[open_]], -1)
        return rank


def replay(words: list[bytes], vocabulary: Vocabulary) -> list[list[int]]:
    """Token ids of each word, all merged together in rank order.

    A word in which a merge brought up a pair of smaller rank waits with its other pairs of the present rank until
    that one is done, so each word sees its merges in the order it would see them alone.
    """
    lengths = np.array([len(w) for w in words], np.int64)
    symbol = vocabulary.first_array[np.frombuffer(b"".join(words), np.uint8)]
    size = len(symbol)
    word_of = np.repeat(np.arange(len(words)), lengths)
    # one slot more than there are symbols: a sentinel to the left and right of every word, whose pairs have no rank
    after, before = np.arange(1, size + 2), np.arange(-1, size)
    ends = np.cumsum(lengths)
    full = lengths > 0
    after[ends[full] - 1] = size
    before[(ends - lengths)[full]] = size
    symbol = np.append(symbol, vocabulary.width)
    first_ranks = vocabulary.rank_of(symbol[:size], symbol[after[:size]])
    index: dict[int, list[int]] = {}
    known = np.flatnonzero(first_ranks >= 0)
    by_rank = known[np.argsort(first_ranks[known], kind="stable")]
    ranks, where = np.unique(first_ranks[by_rank], return_index=True)
    for rank, begin, end in zip(ranks.tolist(), where.tolist(), [*where[1:].tolist(), len(by_rank)]):
        index[rank] = by_rank[begin:end].tolist()
    waiting = list(index)
    heapq.heapify(waiting)
    while waiting:
        rank = heapq.heappop(waiting)
        positions = index.pop(rank, None)
        if positions is None:
            continue
        at = np.array(positions)
        if len(at) > 1:
            at.sort()
        at = at[vocabulary.rank_of(symbol[at], symbol[after[at]]) == rank]
        if len(at) > 1 and (at[1:] == at[:-1]).any():
            at = np.unique(at)
        if len(at) > 1 and (after[at[:-1]] == at[1:]).any():  # overlapping pairs, as in a run of one byte: from the left
            taken, last = [], -1
            for i in at.tolist():
                if i != last:
                    taken.append(i)
                    last = int(after[i])
            at = np.array(taken)
        if not len(at):
            continue
        if len(at) > 1 and (word_of[at[1:]] == word_of[at[:-1]]).any():
            # only the leftmost of a word now; the rest after whatever smaller rank that merge may bring up
            leftmost = np.append(True, word_of[at[1:]] != word_of[at[:-1]])
            rest = at[~leftmost]
            at = at[leftmost]
            index[rank] = rest.tolist()
            heapq.heappush(waiting, rank)
        right = after[at]
        left, beyond = before[at], after[right]
        symbol[at] = rank
        symbol[right] = -1
        after[at] = beyond
        before[beyond] = at
        for place, partner in ((left, at), (at, beyond)):
            new = vocabulary.rank_of(symbol[place], symbol[partner])
            hit = np.flatnonzero(new >= 0)
            for r, i in zip(new[hit].tolist(), place[hit].tolist(), strict=True):
                listed = index.get(r)
                if listed is None:
                    index[r] = [i]
                    heapq.heappush(waiting, r)
                else:
                    listed.append(i)
    alive = symbol[:size] >= 0
    ids = symbol[:size][alive].tolist()
    cuts = np.concatenate([[0], np.cumsum(np.bincount(word_of[alive], minlength=len(words)))]).tolist()
    return [ids[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def pre_tokens(text: str, vocabulary: Vocabulary) -> list[str]:
    return (vocabulary.pattern if BEYOND.search(text) else vocabulary.near).findall(text)


class Encoder:
    """Little-endian 32-bit ids of texts; keeps up to ``room`` encoded pre-tokens."""

    def __init__(self, path: str | None, room: int) -> None:
        self.vocabulary, self.room, self.kept = Vocabulary(path), room, {}

    def _learn(self, words: set[str], into: dict[str, bytes]) -> None:
        block: list[str] = []
        held = 0
        for word in words:
            block.append(word)
            held += len(word)
            if held >= REPLAY_BYTES:
                self._flush(block, into)
                block, held = [], 0
        if block:
            self._flush(block, into)

    def _flush(self, block: list[str], into: dict[str, bytes]) -> None:
        whole = self.vocabulary.whole
        rest = []
        for word in block:
            raw = word.encode()
            single = whole.get(raw)
            if single is None:
                rest.append((word, raw))
            else:
                into[word] = single.to_bytes(4, "little")
        for (word, _), ids in zip(rest, replay([raw for _, raw in rest], self.vocabulary), strict=True):
            into[word] = b"".join(i.to_bytes(4, "little") for i in ids)

    def encode(self, texts: list[str]) -> list[bytes]:
        cut = [pre_tokens(t, self.vocabulary) for t in texts]
        if len(self.kept) > self.room:
            self.kept = {}
        new = {w for words in cut for w in words if w not in self.kept}
        once: dict[str, bytes] = {}
        self._learn({w for w in new if len(w) > LONGEST_KEPT}, once)
        self._learn({w for w in new if len(w) <= LONGEST_KEPT}, self.kept)
        kept = self.kept
        if once:
            return [b"".join([kept[w] if w in kept else once[w] for w in words]) for words in cut]
        return [b"".join(map(kept.__getitem__, words)) for words in cut]


def worker_encoder(path: str | None, room: int) -> Encoder:
    """One encoder for a worker process, so that its tasks share what they have learned."""
    return kept_by_worker(("byte_bpe", path, room), lambda: Encoder(path, room))


def blocks(texts: Iterator[str]) -> Iterator[list[str]]:
    block: list[str] = []
    held = 0
    for text in texts:
        block.append(text)
        held += len(text)
        if held >= BLOCK_CHARS:
            yield block
            block, held = [], 0
    if block:
        yield block


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ranks_path: str | None = None, cache_size: int = 320_000) -> DataFrame:
    """Token ids of every whole text, as (id_col, ids), ids being little-endian unsigned 32-bit integers in one binary.

    A null text counts as empty and gives no ids; null ids and repeated rows are kept; special strings are ordinary
    text. Other columns of ``docs`` are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = worker_encoder(ranks_path, cache_size)
        for batch in batches:
            out: list[bytes] = []
            for block in blocks(t.as_py() or "" for t in batch.column(1)):
                out += encoder.encode(block)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["key", "ids"])

    source = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(run, "key long, ids binary").select(F.col("key").alias(id_col), "ids")


def decoded_bytes(ids: bytes, text: dict[int, bytes]) -> bytes:
    return b"".join(map(text.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def decode(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", ranks_path: str | None = None) -> DataFrame:
    """The bytes that the ids stand for, as (id_col, ids, decoded). Null ids give no bytes; an unknown id is an error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        text = token_bytes(ranks_path)
        for batch in batches:
            decoded = [decoded_bytes(x.as_py() or b"", text) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(decoded, pa.binary())], names=["key", "ids", "decoded"])

    source = encoded.select(F.col(id_col).cast("long").alias("key"), F.col(ids_col).alias("ids"))
    return source.mapInArrow(run, "key long, ids binary, decoded binary").select(F.col("key").alias(id_col), "ids", "decoded")


def round_trip(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ranks_path: str | None = None, cache_size: int = 320_000) -> DataFrame:
    """What ``encode`` and then ``decode`` give, as (id_col, ids, decoded), by one worker instead of two for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = worker_encoder(ranks_path, cache_size)
        text = {i: t for t, i in encoder.vocabulary.whole.items()}
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                ids: list[bytes] = []
                for block in blocks(t.as_py() or "" for t in part.column(1)):
                    ids += encoder.encode(block)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.binary()), pa.array([decoded_bytes(x, text) for x in ids], pa.binary())], names=["key", "ids", "decoded"])

    source = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(run, "key long, ids binary, decoded binary").select(F.col("key").alias(id_col), "ids", "decoded")
