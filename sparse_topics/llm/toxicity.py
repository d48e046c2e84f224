"""Toxicity by weak supervision.

Voters: one for each entry of a mined lexicon (words and word stems whose share among toxic rows of the bounded
labelled sample is higher than among the others, by smoothed log-odds; each entry taken is the strongest for the toxic
rows that few earlier ones cover), voters on how dense the lexicon's words stand, and pattern voters over the whole text
(runs of symbols, exclamation marks, capitals). Labels mine the lexicon and give the share of class 1; they cast no vote.

The generative label model draws a row's hidden class and then its votes: each voter speaks or not with a probability
that depends on the class (its accuracy) and on one other voter (their correlation); which one is the maximum spanning
tree over the voters' conditional mutual information. Expectation-maximisation estimates all of it from the votes of the
labelled and of a bounded number of unlabelled rows, from a start in which more lexicon votes mean class 1. A logistic regression
over the voters' outputs and the density is then trained on the posterior labels, and scores every document.

The fit uses at most ``PER_CLASS`` rows a class, ``UNLABELLED`` others and the bytes that ``quality.labelled_sample``
allows. Defined results: null, empty and wordless texts have no votes and get the score of a text on which no voter
speaks; with nothing to learn from every score is 0; rows with conflicting labels are not learned from; repeated rows
each get a row; empty tables and other columns are fine.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np

PER_CLASS, UNLABELLED, LEXICON, LEAST_ROWS, LEAST_ODDS, LEAST_Z, ROUNDS = 3000, 3000, 60, 4, 1.5, 4.0, 60
COVER = 8  # a row that so many entries cover lends its weight to no further one
LEAST_INFORMATION = 0.05  # nats; voters that share less are taken as independent
STEMS = (5, 6, 7, 8)
DENSITIES = (0.004, 0.008, 0.012)

_WORDS = re.compile(r"[^\W\d_]+")
PATTERNS = {
    "symbol runs": re.compile(r"[*#$%&@]{3}"),
    "exclamations": re.compile(r"!!"),
    "capital words": re.compile(r"\b[A-Z]{4,}\b[^a-z]{1,4}\b[A-Z]{4,}\b"),
    "masked word": re.compile(r"\b[A-Za-z]\*+[A-Za-z]\b"),
}


def _entries(text: str | None) -> set[str]:
    """What the lexicon could hold of a text: whole words (with a closing mark) and stems."""
    out = set()
    for w in set(_WORDS.findall((text or "").lower())):
        if len(w) >= 4:
            out.add(w + "$")
            out.update(w[:n] for n in STEMS if len(w) >= n)
    return out


def _strength(c1: int, c0: int, n1: int, n0: int) -> float:
    """Log-odds lift over its standard error; 0 where the lift is too small."""
    p, q = (c1 + 0.5) / (n1 + 1), (c0 + 0.5) / (n0 + 1)
    lift = math.log(p / (1 - p)) - math.log(q / (1 - q))
    return lift / math.sqrt(1 / (c1 + 0.5) + 1 / (c0 + 0.5)) if lift >= LEAST_ODDS else 0.0


def lexicon(sample: list[tuple[str | None, int]]) -> list[str]:
    """Words and stems that speak for label 1, strongest first, none the start of another."""
    toxic = [t for t, y in sample if y]
    clean = [t for t, y in sample if not y]
    often = Counter(e for t in toxic for e in _entries(t))
    often = {e for e, c in often.items() if c >= LEAST_ROWS}
    against = Counter(e for t in clean for e in _entries(t) & often)
    good = {e for e in often if against[e] <= 0.2 * len(clean)}
    rows: dict[str, set[int]] = {}
    for i, t in enumerate(toxic):
        for e in _entries(t) & good:
            rows.setdefault(e, set()).add(i)
    n1, n0 = len(toxic), len(clean)
    rows = {e: r for e, r in rows.items() if _strength(len(r), against[e], n1, n0) >= LEAST_Z}
    out: list[str] = []
    times: Counter = Counter()
    akin = lambda a, b: a.startswith(b.rstrip("$")) or b.startswith(a.rstrip("$"))
    while rows and len(out) < LEXICON:
        best = max(rows, key=lambda e: (_strength(len(rows[e]), against[e], n1, n0), len(e), e))
        out.append(best)
        times.update(rows[best])
        full = {i for i in rows[best] if times[i] >= COVER}
        rows = {e: left for e, r in rows.items() if not akin(e, best) and _strength(len(left := r - full), against[e], n1, n0) >= LEAST_Z}
    return out


@dataclass
class ToxicityModel:
    words: dict[str, int]
    weights: np.ndarray
    bias: float

    def votes(self, texts: list[str | None]) -> np.ndarray:
        n = len(self.words)
        out = np.zeros((len(texts), n + len(DENSITIES) + len(PATTERNS) + 3), np.float64)
        for i, text in enumerate(texts):
            text = text or ""
            said = Counter(_WORDS.findall(text.lower()))
            hits = 0
            for w, c in said.items():
                entry = self.words.get(w + "$", -1)
                for k in STEMS:
                    if entry >= 0 or len(w) < k:
                        break
                    entry = self.words.get(w[:k], -1)
                if entry >= 0:
                    out[i, entry] = 1.0
                    hits += c
            dense = hits / max(20, sum(said.values()))
            for j, d in enumerate(DENSITIES, n):
                out[i, j] = dense >= d
            for j, p in enumerate(PATTERNS.values(), n + len(DENSITIES)):
                out[i, j] = p.search(text) is not None
            out[i, -3] = not hits
            out[i, -2] = hits >= 2
            out[i, -1] = min(3.0, 100 * dense)
        return out

    def score(self, texts: list[str | None]) -> np.ndarray:
        z = np.clip(self.votes(texts) @ self.weights + self.bias, -40, 40)
        return 1.0 / (1.0 + np.exp(-z))


@dataclass
class LabelModel:
    """P(class), and for each voter P(it speaks | class, what its parent says); a voter without parent has itself as one."""

    prior: float
    parent: np.ndarray
    speaks: np.ndarray  # voter x class x parent's vote

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        v = votes.astype(np.int64)
        at = v[:, self.parent] * (self.parent != np.arange(len(self.parent)))
        voters = np.arange(v.shape[1])
        z = np.full(len(v), math.log(self.prior / (1 - self.prior)))
        for y, sign in ((1, 1.0), (0, -1.0)):
            p = self.speaks[voters, y, at]
            z += sign * np.log(np.where(v == 1, p, 1 - p)).sum(1)
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _tree(pair: np.ndarray) -> np.ndarray:
    """Parent of each voter in the maximum spanning tree of a symmetric matrix; edges under LEAST_INFORMATION are left out."""
    n = len(pair)
    parent = np.arange(n)
    best, source = pair[0].copy(), np.zeros(n, np.int64)
    left = np.ones(n, bool)
    left[0] = False
    for _ in range(n - 1):
        i = int(np.where(left, best, -1.0).argmax())
        if best[i] >= LEAST_INFORMATION:
            parent[i] = source[i]
        left[i] = False
        better = left & (pair[i] > best)
        best[better], source[better] = pair[i][better], i
    return parent


def _estimated(votes: np.ndarray, post: np.ndarray, weight: np.ndarray, prior: float) -> LabelModel:
    n = votes.shape[1]
    total = weight.sum()
    joint = np.zeros((2, n, n, 2, 2))  # class, voter, parent, vote, parent's vote
    mass = np.zeros(2)
    for y, w in ((0, (1 - post) * weight), (1, post * weight)):
        mass[y] = w.sum()
        both = (votes * w[:, None]).T @ votes
        one = np.diag(both)
        joint[y, ..., 1, 1] = both
        joint[y, ..., 1, 0] = one[:, None] - both
        joint[y, ..., 0, 1] = one[None, :] - both
        joint[y, ..., 0, 0] = mass[y] - one[:, None] - one[None, :] + both
    joint = np.maximum(joint, 0) + 0.25
    given = joint / joint.sum((-1, -2), keepdims=True)
    apart = given.sum(-1, keepdims=True) * given.sum(-2, keepdims=True)
    information = (mass[:, None, None] / total * (given * np.log(given / apart)).sum((-1, -2))).sum(0)
    np.fill_diagonal(information, 0)
    parent = _tree(information)
    speaks = np.empty((n, 2, 2))
    for j in range(n):
        for y in (0, 1):
            if parent[j] == j:
                speaks[j, y] = given[y, j, j].sum(-1)[1] if n == 1 else (joint[y, j, j, 1, 1]) / (joint[y, j, j, 1, 1] + joint[y, j, j, 0, 0])
            else:
                t = joint[y, j, parent[j]]
                speaks[j, y] = t[1] / t.sum(0)
    # a voter is no worse than chance: where it speaks less in class 1 than in class 0, its word says nothing
    worse = speaks[:, 1] < speaks[:, 0]
    share = mass[1] / total
    speaks = np.where(worse[:, None, :], (share * speaks[:, 1] + (1 - share) * speaks[:, 0])[:, None, :], speaks)
    return LabelModel(prior, parent, np.clip(speaks, 1e-4, 1 - 1e-4))


def label_model(votes: np.ndarray, prior: float, weight: np.ndarray | None = None, oriented: int | None = None, rounds: int = ROUNDS) -> LabelModel:
    """Estimated from 0/1 votes alone; ``prior`` is the share of class 1, for which the first ``oriented`` voters (all if
    None) speak; nothing is assumed of the others."""
    weight = np.ones(len(votes)) if weight is None else weight
    # the start: the rows with most of those votes, as many as the prior says, are class 1
    said = votes[:, :oriented].sum(1)
    order = np.argsort(-said, kind="stable")
    reach = np.cumsum(weight[order]) <= prior * weight.sum()
    least = max(1.0, said[order][reach].min() if reach.any() else said.max())
    post = np.where(said >= least, 0.9, 0.02)
    model = _estimated(votes, post, weight, prior)
    for _ in range(rounds):
        new = model.posterior(votes)
        done = np.abs(new - post).max() < 1e-4
        post = new
        model = _estimated(votes, post, weight, prior)
        if done:
            break
    return model


def logistic(x: np.ndarray, y: np.ndarray, row_weight: np.ndarray, ridge: float = 0.05, steps: int = 40) -> tuple[np.ndarray, float]:
    """Newton steps on soft labels."""
    a = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(a.shape[1])
    reg = np.full(len(w), ridge)
    reg[-1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -40, 40)))
        g = a.T @ ((p - y) * row_weight) + reg * w
        h = (a * (np.maximum(p * (1 - p), 1e-6) * row_weight)[:, None]).T @ a + np.diag(reg + 1e-6)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w[:-1], float(w[-1])


def fit(sample: list[tuple[str | None, int]], counts: dict[int, int], unlabelled: list[str | None] = ()) -> ToxicityModel:
    words = {w: i for i, w in enumerate(lexicon(sample))}
    model = ToxicityModel(words, np.zeros(len(words) + len(DENSITIES) + len(PATTERNS) + 3), -40.0)
    gold = np.array([y for _, y in sample], np.int64)
    if not len(gold) or gold.min() == gold.max():
        model.bias = 40.0 if len(gold) and gold.min() == 1 else -40.0
        return model
    taken = Counter(gold.tolist())
    rate = np.array([counts[y] / taken[y] for y in gold.tolist()])  # undoes the sampling of the classes
    weight = np.concatenate([rate / rate.mean(), np.ones(len(unlabelled))])
    votes = model.votes([t for t, _ in sample] + list(unlabelled))
    posterior = label_model(votes[:, :-3], counts[1] / (counts[0] + counts[1]), weight, len(words) + len(DENSITIES)).posterior(votes[:, :-3])
    model.weights, model.bias = logistic(votes, posterior, weight)
    return model
