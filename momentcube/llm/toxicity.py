"""Toxicity by weak supervision: voters, a generative label model, and a linear classifier on its posterior labels.

* Voters: lexicons of one word or one word beginning each, mined from the rows that may be learned from (far more frequent in toxic
  rows), and patterns over lexicon words (two kinds, repeated, shouted, beside an address, four or more).
* Label model: a latent class with a vote rate for each voter and class, started from the labels that may be learned from and refined by
  expectation maximisation on votes alone. Correlations between voters that the class doesn't explain are estimated from residuals;
  a voter's evidence is divided by the number of voters that repeat it.
* Classifier: logistic regression on the presence of words and word beginnings, trained on posterior labels; it scores every whole text.

The sample is bounded as in quality_model. Null and empty texts get the bias; without labels all scores are 0.5 minus a hair, and predicted is 0.
Repeated rows are scored each; an empty table gives an empty table; kept columns named like a result give way to it.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame, types as T

from .common import map_rows, texts
from .quality_model import SAMPLE_BYTES, labelled_sample

SAMPLE_ROWS, VOTERS, FEATURES, LEAST_SCORE, PURITY = 4000, 60, 800, 4.5, 0.55
_WORD = re.compile(r"\w+")
STEMS = (3, 4, 5, 6)


def terms_of(text: str) -> set[str]:
    """Words (with a leading =) and their beginnings of three to six letters (with a leading ^)."""
    out = set()
    for w in set(_WORD.findall(text.lower())):
        out.add("=" + w)
        out.update("^" + w[:n] for n in STEMS if len(w) >= n)
    return out


def rated_terms(docs: list[set[str]], y: np.ndarray, least: int = 3) -> list[tuple[float, str]]:
    """Terms more frequent in the (soft) class, by the signed root of the likelihood ratio, highest first.

    Only terms of which more than ``PURITY`` of the rows are in the class: others tell the language or the length of a text.
    """
    on, every = Counter(), Counter()
    for d, p in zip(docs, y):
        every.update(d)
        if p > 0.01:
            on.update(dict.fromkeys(d, p))
    n, n1 = len(y), float(y.sum())
    part = lambda seen, due: seen * np.log(seen / due) if seen > 0 else 0.0
    out = []
    for w, k in on.items():
        m = every[w]
        due = m * n1 / n
        if k >= least and k > PURITY * m and k > due:
            g = part(k, due) + part(m - k, m - due) + part(n1 - k, n1 - due) + part(n - m - n1 + k, n - m - n1 + due)
            out.append((float(np.sqrt(max(2 * g, 0))), w))
    return sorted(out, key=lambda x: (-x[0], x[1]))


def lexicon_voters(docs: list[set[str]], rated: list[tuple[float, str]]) -> list[str]:
    """The best terms; one that marks nearly the same rows as a better one is left out."""
    at: dict[str, set[int]] = {w: set() for z, w in rated[: 20 * VOTERS] if z > LEAST_SCORE}
    for i, d in enumerate(docs):
        for w in d & at.keys():
            at[w].add(i)
    chosen: list[str] = []
    for w in at:
        if len(chosen) < VOTERS and all(len(at[w] & at[v]) < 0.8 * len(at[w] | at[v]) for v in chosen):
            chosen.append(w)
    return chosen


def pattern_votes(text: str, terms: set[str], lexicon: list[str]) -> list[bool]:
    """Patterns over lexicon words: two kinds, a repeated one, a shouted one, one beside an address, four or more."""
    marked = set(lexicon)
    if not terms & marked:
        return [False] * 5
    hits = [w for w in _WORD.findall(text) if "=" + w.lower() in marked or any("^" + w.lower()[:n] in marked for n in STEMS)]
    low = {h.lower() for h in hits}
    return [len(low) >= 2, len(hits) > len(low), any(h.isupper() for h in hits), "=you" in terms and bool(hits), len(hits) >= 4]


def fit_label_model(votes: np.ndarray, start: np.ndarray, rounds: int = 25) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(posterior, vote rates [class][voter], weights) from binary votes; ``start``: first guess of the posterior."""
    n, m = votes.shape
    post, weight = start.astype(float), np.ones(m)
    rate = np.zeros((2, m))
    for _ in range(rounds):
        prior = np.clip(post.mean(), 1e-3, 1 - 1e-3)
        rate[1] = (post @ votes + 0.5) / (post.sum() + 1)
        rate[0] = ((1 - post) @ votes + 0.05) / ((1 - post).sum() + 1)
        residual = votes - (post[:, None] * rate[1] + (1 - post)[:, None] * rate[0])
        spread = np.sqrt((residual**2).mean(axis=0)) + 1e-9
        corr = (residual.T @ residual) / n / np.outer(spread, spread)
        weight = 1 / np.clip(np.where(corr > 0.3, corr, 0), 0, 1).sum(axis=1).clip(1)
        gain = weight * (np.log(rate[1]) - np.log(rate[0]))
        loss = weight * (np.log1p(-rate[1].clip(0, 0.999)) - np.log1p(-rate[0].clip(0, 0.999)))
        z = np.log(prior / (1 - prior)) + votes @ gain + (1 - votes) @ loss
        new = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        if np.abs(new - post).max() < 1e-4:
            post = new
            break
        post = new
    return post, rate, weight


def fit_linear(x: np.ndarray, y: np.ndarray, rounds: int = 200, l2: float = 2e-4) -> tuple[np.ndarray, float]:
    """Logistic regression by accelerated full-batch gradient steps."""
    n, d = x.shape
    w, b, v, vb = np.zeros(d, dtype=np.float32), float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))), np.zeros(d, dtype=np.float32), 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ (w + 0.9 * v) + b + 0.9 * vb, -40, 40)))
        g = p - y
        v = 0.9 * v - 2.0 * (x.T @ g / n + l2 * w)
        vb = 0.9 * vb - 0.2 * g.mean()
        w, b = w + v, b + vb
    return w, float(b)


def train(sample: list[tuple[str, int]]) -> tuple[dict[str, float], float]:
    """(weights of words, bias)."""
    y = np.array([v for _, v in sample], dtype=float)
    if not len(y) or y.min() == y.max():
        return {}, float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1))) - 1e-6 if len(y) else -1e-6
    shared: dict[str, str] = {}  # one string object for each term, whatever the number of documents
    docs = [{shared.setdefault(w, w) for w in terms_of(t)} for t, _ in sample]
    lexicon = lexicon_voters(docs, rated_terms(docs, y))
    votes = np.array([[w in d for w in lexicon] + pattern_votes(t, d, lexicon) for (t, _), d in zip(sample, docs)], dtype=float)
    post, _, _ = fit_label_model(votes, y * 0.9 + 0.05)
    if post.max() - post.min() < 0.5:  # voters that say nothing: the labels that may be learned from stand
        post = y
    chosen = [w for z, w in rated_terms(docs, post) if z > LEAST_SCORE][:FEATURES]
    at = {w: i for i, w in enumerate(chosen)}
    x = np.zeros((len(docs), len(chosen)), dtype=np.float32)
    for i, d in enumerate(docs):
        x[i, [at[w] for w in d & at.keys()]] = 1
    weights, bias = fit_linear(x, post.astype(np.float32))
    return {w: float(weights[i]) for w, i in at.items() if abs(weights[i]) > 1e-3}, bias


def score(text: str, weights: dict[str, float], bias: float) -> float:
    z = bias + sum(weights[w] for w in sorted(weights.keys() & terms_of(text)))
    return float(1 / (1 + np.exp(-np.clip(z, -50, 50))))


def fit(docs: DataFrame, labels: DataFrame, column: str = "toxic") -> tuple[dict[str, float], float]:
    return train(labelled_sample(docs, labels, column, SAMPLE_ROWS, SAMPLE_BYTES))


def scored(docs: DataFrame, model: tuple[dict[str, float], float], keep: list[str], threshold: float = 0.5) -> DataFrame:
    weights, bias = model

    def add(batch):
        s = [score(t, weights, bias) for t in texts(batch)]
        return {"score": s, "predicted": [int(x >= threshold) for x in s]}

    return map_rows(docs, add, [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())], keep)
