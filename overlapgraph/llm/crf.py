"""A small linear-chain conditional random field with named features, for two or more labels."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .langid import _plain_passes, pair_expectations


@dataclass
class ChainModel:
    weights: dict[str, tuple[float, ...]]  # per feature, one weight for each label
    transitions: list[list[float]]

    @property
    def labels(self) -> int:
        return len(self.transitions)


def train(sequences: list[list[list[str]]], labels: list[list[int]], k: int = 2, epochs: int = 12, rate: float = 0.3, l2: float = 1e-4, batch: int = 32, seed: int = 3) -> ChainModel:
    """Likelihood training; a sequence is a list of positions, a position a list of feature names."""
    names: dict[str, int] = {}
    feats = [[[names.setdefault(f, len(names)) for f in pos] for pos in seq] for seq in sequences]
    w, t = np.zeros((len(names), k)), np.zeros((k, k))
    sw, st = np.full((len(names), k), 1e-4), np.full((k, k), 1e-4)
    rng = np.random.default_rng(seed)
    order = np.arange(len(feats))
    for _ in range(epochs):
        rng.shuffle(order)
        for at in range(0, len(order), batch):
            some = [i for i in order[at : at + batch] if feats[i]]
            if not some:
                continue
            gold = np.concatenate([labels[i] for i in some]).astype(int)
            owner = np.repeat(np.arange(len(some)), [len(feats[i]) for i in some])
            flat = [pos for i in some for pos in feats[i]]
            rows = np.repeat(np.arange(len(flat)), [len(p) for p in flat])
            cols = np.fromiter((f for p in flat for f in p), np.int64)
            emit = np.zeros((len(flat), k))
            np.add.at(emit, rows, w[cols])
            psi, trans = np.exp(emit - emit.max(axis=1, keepdims=True)), np.exp(t)
            fore, back = _plain_passes(psi, owner, trans)
            post = fore * back
            post /= post.sum(axis=1, keepdims=True)
            slope = -post
            slope[np.arange(len(gold)), gold] += 1.0
            grad = np.zeros_like(w)
            np.add.at(grad, cols, slope[rows])
            grad = grad / len(some) - l2 * w
            sw += grad**2
            w += rate * grad / np.sqrt(sw)
            same = np.flatnonzero(owner[1:] == owner[:-1])
            real = np.zeros((k, k))
            np.add.at(real, (gold[same], gold[same + 1]), 1.0)
            gt = (real - pair_expectations(emit, owner, t, post)) / len(some)
            st += gt**2
            t += rate * gt / np.sqrt(st)
    return ChainModel({n: tuple(float(x) for x in w[i]) for n, i in names.items()}, t.tolist())


def viterbi(positions: list[list[str]], model: ChainModel, more: list[tuple] | None = None) -> list[int]:
    """The best label sequence; ties go to the smaller label. Features never seen count nothing.

    ``more`` holds, for each position, sums of weights of further features.
    """
    if not positions:
        return []
    k, trans, weights = model.labels, model.transitions, model.weights
    best: list[float] = []
    links: list[list[int]] = []
    labels = range(k)
    for at, feats in enumerate(positions):
        emit = list(more[at]) if more else [0.0] * k
        for f in feats:
            got = weights.get(f)
            if got is not None:
                for c in labels:
                    emit[c] += got[c]
        if not best:
            best = emit
            continue
        new, link = [], []
        for c in labels:
            b = max(labels, key=lambda p: best[p] + trans[p][c])
            link.append(b)
            new.append(best[b] + trans[b][c] + emit[c])
        best = new
        links.append(link)
    out = [max(labels, key=lambda c: best[c])]
    for link in reversed(links):
        out.append(link[out[-1]])
    return out[::-1]
