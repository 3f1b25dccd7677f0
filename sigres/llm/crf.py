"""Linear-chain conditional random fields in numpy: training, Viterbi and forward-backward.

A token belongs to a class, a set of features; its emission is the sum of the weights of its own
features, of those of the token before and of the token after it.  So emissions are computed once
per class and gathered.  Sequences of any length stand end to end in one array; the recursions go
over positions, with all sequences that are still running side by side.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np


class Chain:
    """Running order of sequences that stand end to end: at each position, those that have a token."""

    def __init__(self, lengths: np.ndarray):
        lengths = np.asarray(lengths, np.int64)
        starts = np.cumsum(lengths) - lengths
        order = np.argsort(-lengths, kind="stable")
        self.starts, self.lengths = starts[order], lengths[order]
        self.total = int(lengths.sum())
        most = int(self.lengths[0]) if len(lengths) else 0
        # sequences still running at each position
        self.running = np.searchsorted(-self.lengths, -np.arange(1, most + 1), side="right")

    def first(self) -> np.ndarray:
        return self.starts[self.lengths > 0]

    def inner(self) -> np.ndarray:
        """Tokens that are not the first of their sequence."""
        on = np.ones(self.total, bool)
        on[self.first()] = False
        return np.flatnonzero(on)


class LinearChain:
    """Weights: ``weights[f, place, label]`` with places self, before and after; ``moves``; ``begin``."""

    def __init__(self, labels: Sequence[str], features: dict[str, int]):
        self.labels, self.features = list(labels), features
        k = len(labels)
        self.weights = np.zeros((len(features), 3, k))
        self.moves, self.begin = np.zeros((k, k)), np.zeros(k)

    def class_rows(self, classes: Sequence[Sequence[str]]) -> np.ndarray:
        """Emission parts of each class: (class, place, label)."""
        out = np.zeros((len(classes), 3, len(self.labels)))
        for i, names in enumerate(classes):
            ids = [self.features[n] for n in names if n in self.features]
            if ids:
                out[i] = self.weights[ids].sum(0)
        return out

    def emissions(self, rows: np.ndarray, cls: np.ndarray, chain: Chain) -> np.ndarray:
        e = rows[cls, 0]
        inner = chain.inner()
        e[inner] += rows[cls[inner - 1], 1]
        e[inner - 1] += rows[cls[inner], 2]
        e[chain.first()] += self.begin
        return e

    def marginals(self, e: np.ndarray, chain: Chain, pairs: bool = False):
        """Probability of each label at each token, by scaled forward and backward recursions."""
        x = np.exp(e - e.max(1, keepdims=True)) if len(e) else e
        move = np.exp(self.moves)
        ahead, behind = np.empty_like(x), np.empty_like(x)
        for t, n in enumerate(chain.running):
            at = chain.starts[:n] + t
            a = x[at] if not t else (ahead[at - 1] @ move) * x[at]
            ahead[at] = a / a.sum(1, keepdims=True)
        for t in range(len(chain.running) - 1, -1, -1):
            n = chain.running[t]
            at = chain.starts[:n] + t
            more = chain.running[t + 1] if t + 1 < len(chain.running) else 0
            behind[at[more:]] = 1.0
            if more:
                b = (x[at[:more] + 1] * behind[at[:more] + 1]) @ move.T
                behind[at[:more]] = b / b.sum(1, keepdims=True)
        p = ahead * behind
        p /= np.maximum(p.sum(1, keepdims=True), 1e-300)
        if not pairs:
            return p
        inner = chain.inner()
        joint = ahead[inner - 1][:, :, None] * move[None] * (x[inner] * behind[inner])[:, None, :]
        joint /= joint.sum((1, 2), keepdims=True)
        return p, joint.sum(0)

    def settled(self, e: np.ndarray) -> np.ndarray:
        """Tokens that cannot leave label 0 on a best path: another label would lose more by its
        emission than the best moves into it and out of it could gain over those of label 0.  A
        sequence of only such tokens has label 0 throughout."""
        over = np.maximum(self.moves - self.moves[0, 0], 0)
        gain = over.max(0) + over.max(1)
        return (e[:, :1] - e > gain)[:, 1:].all(1)

    def viterbi(self, e: np.ndarray, chain: Chain) -> np.ndarray:
        """The label of each token on the best path of its sequence."""
        best, back = e.copy(), np.zeros(e.shape, np.int8)
        for t, n in enumerate(chain.running[1:], 1):
            at = chain.starts[:n] + t
            step = best[at - 1][:, :, None] + self.moves[None]
            back[at] = step.argmax(1)
            best[at] += step.max(1)
        out = np.zeros(len(e), np.int64)
        for t in range(len(chain.running) - 1, -1, -1):
            n = chain.running[t]
            at = chain.starts[:n] + t
            more = chain.running[t + 1] if t + 1 < len(chain.running) else 0
            out[at[more:]] = best[at[more:]].argmax(1)
            if more:
                out[at[:more]] = back[at[:more] + 1, out[at[:more] + 1]]
        return out


def train(sequences: Sequence[tuple[Sequence[str], Sequence[str]]], describe: Callable[[str], Sequence[str]],
          labels: Sequence[str], rounds: int = 120, rate: float = 0.15, ridge: float = 1e-3) -> LinearChain:
    """Maximum-likelihood weights from (tokens, labels) sequences, by Adam on the whole table."""
    names: dict[str, int] = {}
    classes: dict[str, int] = {}
    member, feature = [], []
    for tokens, _ in sequences:
        for w in tokens:
            if w not in classes:
                classes[w] = len(classes)
                for f in describe(w):
                    member.append(classes[w])
                    feature.append(names.setdefault(f, len(names)))
    model = LinearChain(labels, names)
    cls = np.array([classes[w] for tokens, _ in sequences for w in tokens], np.int64)
    truth = np.array([model.labels.index(y) for _, ys in sequences for y in ys], np.int64)
    chain = Chain([len(t) for t, _ in sequences])
    member, feature = np.array(member), np.array(feature)
    inner, first, k = chain.inner(), chain.first(), len(model.labels)
    want = np.eye(k)[truth]
    moves = np.zeros((k, k))
    np.add.at(moves, (truth[inner - 1], truth[inner]), 1)
    state = [(p, np.zeros_like(p), np.zeros_like(p)) for p in (model.weights, model.moves, model.begin)]
    for step in range(1, rounds + 1):
        rows = _sums(member, model.weights[feature], len(classes))
        p, pairs = model.marginals(model.emissions(rows, cls, chain), chain, pairs=True)
        off = (p - want) / len(sequences)
        by_class = np.stack([_sums(cls, off, len(classes)), _sums(cls[inner - 1], off[inner], len(classes)),
                             _sums(cls[inner], off[inner - 1], len(classes))], 1)
        dw = _sums(feature, by_class[member], len(names))
        grads = (dw, (pairs - moves) / len(sequences), off[first].sum(0))
        for (value, m, v), g in zip(state, grads):
            g = g + ridge * value
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            value -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return model


def _sums(group: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows of ``values`` that have the same group number."""
    flat = values.reshape(len(values), -1)
    out = np.stack([np.bincount(group, flat[:, j], n) for j in range(flat.shape[1])], 1)
    return out.reshape(n, *values.shape[1:])


class TokenClasses:
    """Tokens -> class numbers with their emission parts, remembered up to a bound.

    ``key`` maps a token to what its features depend on, so tokens of one shape share a class.
    """

    def __init__(self, model: LinearChain, describe: Callable[[str], Sequence[str]], key: Callable[[str], str],
                 most: int = 200_000):
        self.model, self.describe, self.key, self.most = model, describe, key, most
        self._clear()

    def _clear(self) -> None:
        self.tokens: dict[str, int] = {}
        self.keys: dict[str, int] = {}
        self.rows = np.zeros((256, 3, len(self.model.labels)))

    def numbers(self, tokens: list[str]) -> np.ndarray:
        if len(self.tokens) > self.most or len(self.keys) > self.most:
            self._clear()
        known = self.tokens
        for w in set(tokens).difference(known):
            key = self.key(w)
            at = self.keys.get(key)
            if at is None:
                at = self.keys[key] = len(self.keys)
                if at >= len(self.rows):
                    self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
                self.rows[at] = self.model.class_rows([self.describe(w)])[0]
            known[w] = at
        return np.fromiter(map(known.__getitem__, tokens), np.int64, len(tokens))
