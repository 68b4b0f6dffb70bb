"""A linear-chain conditional random field in numpy: sparse indicator features, exact gradients, batched Viterbi."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class ChainModel:
    """``weights`` (features x labels) and ``moves`` (label x next label); feature names map to rows."""

    labels: tuple[str, ...]
    index: dict[str, int]
    weights: np.ndarray
    moves: np.ndarray

    def emissions(self, features: list[list[str]]) -> np.ndarray:
        out = np.zeros((len(features), len(self.labels)))
        for row, names in enumerate(features):
            known = [self.index[f] for f in names if f in self.index]
            if known:
                out[row] = self.weights[known].sum(axis=0)
        return out


def _logsumexp(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return np.squeeze(top, axis) + np.log(np.exp(x - top).sum(axis=axis))


def fit(sentences: list[tuple[list[list[str]], list[str]]], labels: tuple[str, ...], steps: int = 120, rate: float = 0.25, l2: float = 0.002) -> ChainModel:
    """Maximum likelihood with an L2 penalty, full-batch Adam; sentences are padded to one length and run together."""
    names = sorted({f for feats, _ in sentences for row in feats for f in row})
    index = {f: i for i, f in enumerate(names)}
    s, t, k = len(sentences), max(len(tags) for _, tags in sentences), len(labels)
    where, feat, gold = [], [], np.zeros((s, t), int)
    mask = np.zeros((s, t), bool)
    for i, (feats, tags) in enumerate(sentences):
        for j, (row, tag) in enumerate(zip(feats, tags, strict=True)):
            mask[i, j], gold[i, j] = True, labels.index(tag)
            where += [i * t + j] * len(row)
            feat += [index[f] for f in row]
    where, feat = np.array(where), np.array(feat)
    weights, moves = np.zeros((len(names), k)), np.zeros((k, k))
    onehot = np.eye(k)[gold] * mask[..., None]
    pairs = mask[:, 1:] & mask[:, :-1]
    gold_moves = np.einsum("sti,stj->ij", onehot[:, :-1] * pairs[..., None], onehot[:, 1:])
    m = [np.zeros_like(weights), np.zeros_like(moves)]
    v = [np.zeros_like(weights), np.zeros_like(moves)]
    for step in range(1, steps + 1):
        emit = np.zeros((s * t, k))
        np.add.at(emit, where, weights[feat])
        emit = emit.reshape(s, t, k)
        ahead, back = np.zeros((s, t, k)), np.zeros((s, t, k))
        ahead[:, 0] = emit[:, 0]
        for j in range(1, t):
            ahead[:, j] = np.where(mask[:, j, None], _logsumexp(ahead[:, j - 1][:, :, None] + moves, 1) + emit[:, j], ahead[:, j - 1])
        for j in range(t - 2, -1, -1):
            back[:, j] = np.where(mask[:, j + 1, None], _logsumexp(moves[None] + (emit[:, j + 1] + back[:, j + 1])[:, None, :], 2), 0)
        total = _logsumexp(ahead[:, -1], 1)
        seen = np.exp(ahead + back - total[:, None, None]) * mask[..., None]
        joint = np.exp(ahead[:, :-1, :, None] + moves + (emit[:, 1:] + back[:, 1:])[:, :, None, :] - total[:, None, None, None]) * pairs[..., None, None]
        by_token = (onehot - seen).reshape(s * t, k) / s
        g_w = np.zeros_like(weights)
        np.add.at(g_w, feat, by_token[where])
        for i, (param, grad) in enumerate(((weights, g_w - l2 * weights), (moves, (gold_moves - joint.sum((0, 1))) / s - l2 * moves))):
            m[i] = 0.9 * m[i] + 0.1 * grad
            v[i] = 0.99 * v[i] + 0.01 * grad**2
            param += rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.99**step)) + 1e-8)
    return ChainModel(labels, index, weights, moves)


def viterbi(model: ChainModel, emit: np.ndarray, lengths: np.ndarray) -> list[np.ndarray]:
    """Best label paths of many sequences at once; ``emit`` holds their rows one after another."""
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype(int)
    order = np.argsort(-lengths, kind="stable")
    paths: list[np.ndarray] = [np.empty(0, int)] * len(lengths)
    k = emit.shape[1]
    for at in range(0, len(order), 4096):
        own = order[at : at + 4096]
        own = own[lengths[own] > 0]
        if not len(own):
            continue
        n, t = lengths[own], int(lengths[own].max())
        back = np.zeros((t, len(own), k), np.int8)
        score = emit[starts[own]].copy()
        for j in range(1, t):
            live = int(np.searchsorted(-n, -j, side="left"))  # sequences are sorted from long to short
            step = score[:live, :, None] + model.moves
            back[j, :live] = step.argmax(axis=1)
            score[:live] = step.max(axis=1) + emit[starts[own[:live]] + j]
        for row, i in enumerate(own):
            path, last = np.empty(n[row], int), score[row].argmax()
            for j in range(n[row] - 1, -1, -1):
                path[j] = last
                last = back[j, row, last]
            paths[i] = path
    return paths


def always(model: ChainModel, emit: np.ndarray, label: int = 0) -> np.ndarray:
    """Positions that carry ``label`` on every best path whatever surrounds them.

    Putting ``label`` in place of another label ``y`` changes a path's score by at least the emission gap plus the
    least favourable change of the two moves around; where that is positive for all ``y``, the sequence may be cut.
    """
    gap = model.moves[:, [label]] - model.moves  # into: label instead of y
    away = model.moves[[label], :] - model.moves  # out of
    worst = gap.min(axis=0) + away.min(axis=1)
    loss = emit[:, [label]] - emit + np.minimum(gap.min(axis=0), 0) + np.minimum(away.min(axis=1), 0)
    loss = np.minimum(loss, emit[:, [label]] - emit + worst)
    loss[:, label] = np.inf
    return loss.min(axis=1) > 1e-9
