"""Linear-chain conditional random fields in numpy: marginals by a blocked scan, training, and Viterbi in batches."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

BLOCK = 128
#: Tokens whose matrices are held at a time where only their chances are asked for.
SLAB = 1 << 16


def _products(m: np.ndarray, step: int) -> np.ndarray:
    """Running matrix products along axis 1 of [blocks, length, 2, 2], from the left (step 1) or from the right (step -1), each scaled to a largest entry of 1."""
    out = np.empty_like(m)
    order = range(m.shape[1])[::step]
    for n, i in enumerate(order):
        if n == 0:
            out[:, i] = m[:, i]
        else:
            a, b = (out[:, i - 1], m[:, i]) if step == 1 else (m[:, i], out[:, i + 1])
            out[:, i] = a[:, :, :1] * b[:, :1, :] + a[:, :, 1:] * b[:, 1:, :]
        out[:, i] /= out[:, i].max(axis=(1, 2), keepdims=True)
    return out


def _matrices(odds: np.ndarray, first: np.ndarray, step: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(emissions [blocks * BLOCK, 2], matrices [blocks, BLOCK, 2, 2]); what fills the last block begins a sequence each."""
    n = len(odds)
    blocks = -(-n // BLOCK)
    x = np.zeros(blocks * BLOCK)
    x[:n] = np.clip(odds, -60, 60)
    begins = np.ones(blocks * BLOCK, bool)
    begins[:n] = first
    emit = np.stack([np.exp(-np.maximum(x, 0)), np.exp(np.minimum(x, 0))], axis=1)
    m = np.where(begins[:, None, None], begin[None, None, :], step[None]) * emit[:, None, :]
    return emit, m.reshape(blocks, BLOCK, 2, 2)


def _chained(totals: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """From the product of every block: what comes in ahead of each from the left, and behind each from the right."""
    ahead, behind = np.empty((len(totals), 2)), np.empty((len(totals), 2))
    rows = totals.tolist()
    p, q = 0.5, 0.5
    for k, ((a, b), (c, d)) in enumerate(rows):
        ahead[k] = p, q
        p, q = p * a + q * c, p * b + q * d
        total = p + q
        p, q = p / total, q / total
    p, q = 1.0, 1.0
    for k in range(len(rows) - 1, -1, -1):
        behind[k] = p, q
        (a, b), (c, d) = rows[k]
        p, q = a * p + b * q, c * p + d * q
        total = p + q
        p, q = p / total, q / total
    return ahead, behind


def _both_ways(m: np.ndarray, left: np.ndarray, ahead: np.ndarray, behind: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Forward and backward values of every token, each pair scaled to a sum of 1."""
    alpha = ahead[:, None, :1] * left[:, :, 0] + ahead[:, None, 1:] * left[:, :, 1]
    alpha /= alpha.sum(axis=2, keepdims=True)
    right = _products(m, -1)
    beta = np.empty((len(m), BLOCK, 2))
    beta[:, -1] = behind
    beta[:, :-1] = right[:, 1:, :, 0] * behind[:, None, :1] + right[:, 1:, :, 1] * behind[:, None, 1:]
    beta /= beta.sum(axis=2, keepdims=True)
    return alpha.reshape(-1, 2), beta.reshape(-1, 2)


def marginals(odds: np.ndarray, first: np.ndarray, transition: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(probability of state 1 of every token, expected transitions [2, 2] and starts as a [3, 2] array).

    odds: score of state 1 above state 0. first: where a sequence begins; sequences stand one after another.
    A token that begins a sequence has a matrix of equal rows, so nothing passes from one sequence to the next
    and one scan serves all of them: products within blocks are vectorised over blocks, and only the blocks'
    products are chained in a loop.
    """
    n = len(odds)
    if not n:
        return np.zeros(0), np.zeros((3, 2))
    step, begin = np.exp(transition - transition.max()), np.exp(start - start.max())
    emit, m = _matrices(odds, first, step, begin)
    left = _products(m, 1)
    alpha, beta = _both_ways(m, left, *_chained(left[:, -1]))
    alpha, beta = alpha[:n], beta[:n]
    both = alpha * beta
    chance = both[:, 1] / both.sum(axis=1)
    pairs = np.zeros((3, 2))
    inner = np.flatnonzero(~first[:n])
    if len(inner):
        joint = alpha[inner - 1][:, :, None] * step[None] * (emit[inner] * beta[inner])[:, None, :]
        pairs[:2] = (joint / joint.sum(axis=(1, 2), keepdims=True)).sum(axis=0)
    pairs[2] = 1 - chance[first[:n]].sum() / max(1, first[:n].sum()), chance[first[:n]].sum() / max(1, first[:n].sum())
    pairs[2] *= first[:n].sum()
    return chance, pairs


def chances(odds: np.ndarray, first: np.ndarray, transition: np.ndarray, start: np.ndarray) -> np.ndarray:
    """The probabilities of marginals() alone, a slab of tokens at a time: one pass for the blocks' products, which are chained over all slabs, and one for the tokens."""
    step, begin = np.exp(transition - transition.max()), np.exp(start - start.max())
    slabs = [slice(a, min(a + SLAB, len(odds))) for a in range(0, len(odds), SLAB)]
    if not slabs:
        return np.zeros(0)
    kept, totals = None, []
    for part in slabs:
        m = _matrices(odds[part], first[part], step, begin)[1]
        left = _products(m, 1)
        totals.append(left[:, -1].copy())
        kept = (m, left) if len(slabs) == 1 else None
    ahead, behind = _chained(np.concatenate(totals))
    out, at = [], 0
    for part, total in zip(slabs, totals, strict=True):
        m, left = kept or ((m := _matrices(odds[part], first[part], step, begin)[1]), _products(m, 1))
        own = slice(at, at + len(total))
        alpha, beta = _both_ways(m, left, ahead[own], behind[own])
        both = (alpha * beta)[: part.stop - part.start]
        out.append(both[:, 1] / both.sum(axis=1))
        at += len(total)
    return np.concatenate(out)


@dataclass
class BinaryCRF:
    """Two states; the score of state 1 of a token is the sum of the weights of its features."""

    weights: np.ndarray
    transition: np.ndarray
    start: np.ndarray

    def chances(self, features: np.ndarray, first: np.ndarray) -> np.ndarray:
        """features: one row of weight indices per token."""
        odds = np.zeros(len(features))
        for column in features.T:
            odds += self.weights[column]
        return chances(odds, first, self.transition, self.start)


def train_binary(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]], size: int, rounds: int = 20, rate: float = 0.5, decay: float = 1e-6) -> BinaryCRF:
    """Maximum likelihood by Adam on whole passes. parts: (features, first, labels) in pieces that bound the memory of a step."""
    model = BinaryCRF(np.zeros(size), np.zeros((2, 2)), np.zeros(2))
    seen: dict[str, np.ndarray] = {}
    total = max(1, sum(len(y) for _, _, y in parts))
    for n in range(1, rounds + 1):
        slope_w, slope_t, slope_s = -decay * model.weights, np.zeros((2, 2)), np.zeros(2)
        for features, first, labels in parts:
            odds = sum(model.weights[c] for c in features.T)
            chance, pairs = marginals(odds, first, model.transition, model.start)
            error = (labels - chance) / total
            for column in features.T:
                slope_w += np.bincount(column, error, minlength=size)
            inner = np.flatnonzero(~first)
            seen_pairs = np.bincount(labels[inner - 1].astype(int) * 2 + labels[inner].astype(int), minlength=4).reshape(2, 2)
            slope_t += (seen_pairs - pairs[:2]) / total
            slope_s += (np.bincount(labels[first].astype(int), minlength=2) - pairs[2]) / total
        for name, value, slope in (("w", model.weights, slope_w), ("t", model.transition, slope_t), ("s", model.start, slope_s)):
            m = seen.setdefault(f"{name}m", np.zeros_like(value))
            v = seen.setdefault(f"{name}v", np.zeros_like(value))
            m += 0.1 * (slope - m)
            v += 0.01 * (slope * slope - v)
            value += rate * (m / (1 - 0.9**n)) / (np.sqrt(v / (1 - 0.99**n)) + 1e-9)
    return model


def viterbi(emission: np.ndarray, lengths: np.ndarray, transition: np.ndarray) -> np.ndarray:
    """Best state of every token. emission [tokens, states], sequences one after another with these lengths; the first and last state take no extra score. Ties go to the smaller state."""
    out = np.zeros(len(emission), np.int64)
    starts = np.cumsum(lengths) - lengths
    order = np.argsort(-lengths, kind="stable")
    lengths_down, starts_down = lengths[order], starts[order]
    if not len(lengths) or not lengths_down[0]:
        return out
    longest = int(lengths_down[0])
    live = np.searchsorted(-lengths_down, -np.arange(longest), "left")  # sequences longer than t
    score = emission[starts_down[: live[0]]]
    back: list[np.ndarray] = []
    final = np.zeros(live[0], np.int64)
    for t in range(1, longest + 1):
        n = int(live[t]) if t < longest else 0
        final[n : len(score)] = np.argmax(score[n:], axis=1)
        if not n:
            break
        paths = score[:n, :, None] + transition[None]
        back.append(np.argmax(paths, axis=1))
        score = np.take_along_axis(paths, back[-1][:, None, :], axis=1)[:, 0] + emission[starts_down[:n] + t]
    state = final
    for t in range(longest - 1, -1, -1):
        n = int(live[t])
        out[starts_down[:n] + t] = state[:n]
        if t:
            before = state.copy()
            before[:n] = back[t - 1][np.arange(n), state[:n]]
            state = before
    return out
