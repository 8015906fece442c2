"""Generative label model for weak supervision: voters vote 1, -1 or abstain (0); expectation-maximisation finds their accuracies.

Input is a histogram of vote patterns, so its size depends on the number of voters and not on the number of documents.
The model is P(label) times, for each voter, P(vote | label, vote of the voter it depends on). Which voter depends on which is
a forest over the pairs with the largest mutual information within the classes of the first guess (a label fitted without
the dependences would take on what repeated voters say); a pair enters it only if that information is beyond chance. A voter that repeats another one's votes so adds nothing to what the other one says.

The start is worth `smoothing` documents for each label, whatever the corpus: it says which way votes point and no more.
"""

from __future__ import annotations

import numpy as np

#: A pair depends if twice the number of documents times its information exceeds this (8 degrees of freedom, p about 1e-5).
BEYOND_CHANCE = 40.0


class LabelModel:
    """P(vote | label, vote depended on) for each voter, and the prior of label 1."""

    def __init__(self, prior: float = 0.5, smoothing: float = 2.0, steps: int = 200, dependent: bool = True, start: dict | None = None):
        """`start` holds, for label 0 and 1, shares of votes -1, 0 and 1; without it, voters start as right four times out of five."""
        self.prior, self.smoothing, self.steps, self.dependent, self.start = prior, smoothing, steps, dependent, start

    def fit(self, votes: np.ndarray, counts: np.ndarray, anchor: np.ndarray | None = None) -> LabelModel:
        """`votes` (patterns x voters) in {-1, 0, 1} with `counts`; `anchor`, where given, is a first guess of P(label 1) per pattern."""
        votes, counts = np.asarray(votes, np.int64), np.asarray(counts, float)
        n, m = votes.shape
        one_hot = (votes[:, :, None] == np.array([-1, 0, 1])).astype(float)  # patterns x voters x vote
        share = (one_hot * counts[:, None, None]).sum(0) + 1.0 if n else np.ones((m, 3))
        share /= share.sum(1, keepdims=True)
        if self.start is None:
            first = [share * [0.8, 1, 0.2], share * [0.2, 1, 0.8]]
        else:
            first = [np.tile(np.asarray(self.start[label], float), (m, 1)) for label in (0, 1)]
        self._first = np.stack([x / x.sum(1, keepdims=True) for x in first])  # label x voters x vote
        self.parent = np.full(m, -1)
        self.table = np.repeat(self._first[:, :, None, :], 3, axis=2)  # label x voters x vote depended on x vote
        if n == 0 or counts.sum() == 0:
            return self
        p = self.posterior(votes) if anchor is None else np.asarray(anchor, float)
        if self.dependent and m > 1:
            self.parent = self._forest(one_hot, counts, p)
        self._maximise(votes, one_hot, counts, p)
        return self

    def _maximise(self, votes, one_hot, counts, p) -> None:
        """Rounds of maximisation and expectation from a guess of the labels on."""
        before = one_hot[:, self.parent] * (self.parent >= 0)[None, :, None]
        before[:, self.parent < 0, 0] = 1.0  # voters that depend on none
        for _ in range(self.steps):
            for label, weight in ((1, counts * p), (0, counts * (1 - p))):
                joint = np.einsum("nvp,nvx->vpx", before * weight[:, None, None], one_hot, optimize=True)
                alone = np.einsum("nvx,n->vx", one_hot, weight) + self.smoothing * self._first[label]
                alone /= alone.sum(1, keepdims=True)
                joint += self.smoothing * alone[:, None, :]  # votes seldom seen together fall back on the voter's own
                self.table[label] = joint / joint.sum(2, keepdims=True)
            self.prior = float((counts * p).sum() + 1.0) / float(counts.sum() + 2.0)
            was, p = p, self.posterior(votes)
            if np.abs(was - p).max() < 1e-6:
                break
        self.alone = np.stack([np.einsum("nvx,n->vx", one_hot, w) + self.smoothing * self._first[label] for label, w in ((0, counts * (1 - p)), (1, counts * p))])
        self.alone /= self.alone.sum(2, keepdims=True)

    @staticmethod
    def _forest(one_hot, counts, p) -> np.ndarray:
        """Per voter the one it depends on (-1: none): the spanning forest of most information, given the label."""
        n, m, _ = one_hot.shape
        flat = one_hot.reshape(n, 3 * m)
        gain = np.zeros((m, m))
        for weight in (counts * p, counts * (1 - p)):
            total = weight.sum()
            if total < 1:
                continue
            joint = (flat * weight[:, None]).T @ flat / total
            own = np.diag(joint)
            with np.errstate(divide="ignore", invalid="ignore"):
                part = np.where(joint > 0, joint * np.log(joint / np.outer(own, own)), 0.0)
            gain += 2 * total * part.reshape(m, 3, m, 3).sum((1, 3))
        np.fill_diagonal(gain, 0)
        parent, best, source = np.full(m, -1), np.full(m, -np.inf), np.full(m, -1)
        left = np.ones(m, bool)
        while left.any():  # grow trees along the strongest ties
            k = int(np.argmax(np.where(left, best, -np.inf))) if (best[left] > BEYOND_CHANCE).any() else int(np.argmax(np.where(left, gain.sum(1), -np.inf)))
            parent[k] = source[k] if best[k] > BEYOND_CHANCE else -1
            left[k] = False
            near = left & (gain[k] > best)
            best[near], source[near] = gain[k][near], k
        return parent

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        """P(label 1) of each row of votes."""
        votes = np.asarray(votes, np.int64) + 1
        m = votes.shape[1]
        before = np.where(self.parent >= 0, votes[:, self.parent], 0) if m else votes
        odds = np.log(self.table[1] / self.table[0])  # voters x vote depended on x vote
        score = odds[np.arange(m), before, votes].sum(1) + np.log(self.prior / (1 - self.prior))
        return 1 / (1 + np.exp(-np.clip(score, -60, 60)))

    def accuracies(self) -> np.ndarray:
        """Of each voter, the probability of being right when it votes."""
        right = self.prior * self.alone[1, :, 2] + (1 - self.prior) * self.alone[0, :, 0]
        wrong = self.prior * self.alone[1, :, 0] + (1 - self.prior) * self.alone[0, :, 2]
        return right / (right + wrong)
