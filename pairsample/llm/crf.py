"""Linear-chain conditional random fields in arrays: forward-backward, Viterbi and training by stochastic gradient.

Items (words, blocks) have sparse binary features given by hashed numbers. Sequences are padded and handled side by side, one array
operation per position.
"""

from __future__ import annotations

from zlib import crc32

import numpy as np


def hashed(names: list[str], width: int) -> list[int]:
    return [crc32(n.encode()) % width for n in names]


class Chain:
    """Weights of a linear chain: one row per feature, one column per label, and the transitions."""

    def __init__(self, width: int, labels: int) -> None:
        self.weight = np.zeros((width, labels), np.float32)
        self.step = np.zeros((labels, labels), np.float32)
        self.start = np.zeros(labels, np.float32)

    def emissions(self, features: list[list[int]]) -> np.ndarray:
        """One row of label scores per item; every item has at least one feature."""
        if not features:
            return np.zeros((0, self.start.size), np.float32)
        sizes = np.array([len(f) for f in features])
        flat = np.fromiter((x for f in features for x in f), np.int64, int(sizes.sum()))
        return np.add.reduceat(self.weight[flat], np.concatenate([[0], np.cumsum(sizes)[:-1]]), axis=0)

    def forward_backward(self, emission: np.ndarray, lengths: np.ndarray, pairs: bool = False):
        """Label probabilities of padded sequences, emission being (steps, sequences, labels).

        With ``pairs`` also the expected counts of starts and of transitions, summed over all sequences.
        """
        steps, n, labels = emission.shape
        seen = np.exp(emission - emission.max(axis=2, keepdims=True))
        move, alpha = np.exp(self.step), np.empty_like(seen)
        ahead = np.exp(self.start) * seen[0]
        alpha[0] = ahead / ahead.sum(axis=1, keepdims=True)
        for t in range(1, steps):
            ahead = (alpha[t - 1] @ move) * seen[t]
            alpha[t] = ahead / ahead.sum(axis=1, keepdims=True)
        beta = np.ones((n, labels), seen.dtype)
        out = np.empty_like(seen)
        expected = np.zeros((labels, labels))
        for t in range(steps - 1, -1, -1):
            joint = alpha[t] * beta
            out[t] = joint / joint.sum(axis=1, keepdims=True)
            if t:
                later = seen[t] * beta
                inside = (t < lengths)[:, None]
                if pairs:
                    both = alpha[t - 1][:, :, None] * move[None] * later[:, None, :]
                    both /= both.sum(axis=(1, 2), keepdims=True)
                    expected += (both * inside[:, :, None]).sum(axis=0)
                back = later @ move.T
                # beyond its end a sequence carries ones, so that its last item starts from ones
                beta = np.where(inside, back / back.sum(axis=1, keepdims=True), 1.0).astype(seen.dtype)
        return (out, out[0].sum(axis=0), expected) if pairs else out

    def viterbi_all(self, emission: np.ndarray, lengths: np.ndarray) -> list[list[int]]:
        """The best labels of padded sequences, emission being (steps, sequences, labels); the smaller label where two are equal."""
        steps, n, labels = emission.shape
        best, come = self.start + emission[0], np.zeros((steps, n, labels), np.int64)
        for t in range(1, steps):
            paths = best[:, :, None] + self.step[None]
            come[t] = paths.argmax(axis=1)
            best = np.where((t < lengths)[:, None], paths.max(axis=1) + emission[t], best)
        now, out = best.argmax(axis=1), np.zeros((steps, n), np.int64)
        for t in range(steps - 1, -1, -1):
            out[t] = now
            now = np.where(t < lengths, come[t, np.arange(n), now], now) if t else now
        return [out[: lengths[i], i].tolist() for i in range(n)]

    def fit(self, features: list[list[int]], sequences: list[tuple[np.ndarray, np.ndarray]], rounds: int = 3, size: int = 128, rate: float = 0.2, decay: float = 1e-5, seed: int = 7) -> Chain:
        """Adagrad on the log likelihood. ``sequences`` hold item numbers (of ``features``) and labels."""
        rng = np.random.default_rng(seed)
        sizes = np.array([len(f) for f in features])
        flat = np.fromiter((x for f in features for x in f), np.int64, int(sizes.sum()))
        starts = np.cumsum(sizes) - sizes
        squares = [np.full(x.shape, 1e-6) for x in (self.weight, self.step, self.start)]
        for _ in range(rounds):
            order = rng.permutation(len(sequences))
            for at in range(0, len(order), size):
                batch = [sequences[i] for i in order[at : at + size]]
                truth = np.concatenate([y for _, y in batch])
                lengths = np.array([len(s) for s, _ in batch])
                # only the items and features of this batch are touched
                items, place = np.unique(np.concatenate([s for s, _ in batch]), return_inverse=True)
                first_of = np.cumsum(sizes[items]) - sizes[items]
                used = flat[np.repeat(starts[items] - first_of, sizes[items]) + np.arange(sizes[items].sum())]
                scores = np.add.reduceat(self.weight[used], first_of, axis=0)
                emission, where = padded(scores[place], lengths)
                prob, first, moved = self.forward_backward(emission, lengths, pairs=True)
                off = prob[where]
                off[np.arange(len(truth)), truth] -= 1
                by_item = np.stack([np.bincount(place, off[:, k], len(items)) for k in range(off.shape[1])], axis=1)
                touched, spot = np.unique(used, return_inverse=True)
                spread = np.repeat(by_item, sizes[items], axis=0)
                slope = np.stack([np.bincount(spot, spread[:, k], len(touched)) for k in range(off.shape[1])], axis=1)
                for s, y in batch:
                    np.add.at(moved, (y[:-1], y[1:]), -1)
                    first[y[0]] -= 1
                every = slice(None)
                for value, grad, square, rows in zip((self.weight, self.step, self.start), (slope, moved, first), squares, (touched, every, every), strict=True):
                    grad = grad / len(batch) + decay * value[rows]
                    square[rows] += grad * grad
                    value[rows] -= (rate * grad / np.sqrt(square[rows])).astype(np.float32)
        return self


def padded(rows: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray]]:
    """Rows of sequences laid one after another as (steps, sequences, labels), and where each row went."""
    of = np.repeat(np.arange(len(lengths)), lengths)
    step = np.arange(len(rows)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    out = np.zeros((int(lengths.max()), len(lengths), rows.shape[1]), rows.dtype)
    out[step, of] = rows
    return out, (step, of)
