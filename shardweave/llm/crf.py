"""Quality by a linear-chain conditional random field over the lines of a text.

Every line is good or bad. Its features describe the line and its neighbours; transitions tie labels of successive
lines. Lines of labelled texts take the text's label for training. A text's quality is the mean of its lines' marginals
for good, from the forward-backward recursion, weighted by length; a logistic curve sets it against the labels.

The field is fitted on a bounded sample of labelled rows (``FIT_ROWS``); scoring reads every text whole, in one pass
without a shuffle.

Defined cases: null, empty and blank texts have no line and quality zero before the curve; null labels are not learnt
from; with one class only, scores are all 0.5; repeated rows score alike; an empty table gives an empty result; other columns
take no part. A labelled text of very many lines is a group of its own when the field is fitted.
"""

from __future__ import annotations

import operator
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shardweave.llm.kneser_ney import labelled, logistic
from shardweave.staging import stage

FIT_ROWS = 4000
#: Chains, and lines with padding, that one step of the fit holds at a time (one longer chain is held alone).
GROUP_CHAINS, GROUP_LINES = 256, 1 << 17
_SYMBOLS, _UPPER, _DIGITS, _LETTERS = b"#*$%&|<>", bytes(range(65, 91)), bytes(range(48, 58)), bytes([*range(65, 91), *range(97, 123), *range(128, 256)])
#: The neighbours' features that a line sees besides its own.
SHARED = (2, 3, 4, 6, 8, 9)
WIDTH = 11


def lines(text: bytes | None) -> tuple[np.ndarray, np.ndarray]:
    """Features and lengths of the lines of a text that hold a word."""
    rows, sizes, seen = [], [], set()
    for line in (text or b"").split(b"\n"):
        w = line.split()
        if not w:
            continue
        n, size = len(w), len(line)
        again = line in seen
        seen.add(line)
        count = lambda marks: (size - len(line.translate(None, marks)))  # noqa: E731, B023
        rows.append((
            min(np.log1p(n), 8.0), min(size / n, 30.0) / 10, 1 - len(set(w)) / n, sum(map(operator.eq, w, w[1:])) / n, min(count(_SYMBOLS) / n, 3.0),
            count(_UPPER) / size, min(line.count(b"!") / n, 2.0), count(_DIGITS) / size, float(again), float(count(_LETTERS) / size < 0.5), float(n < 3),
        ))
        sizes.append(size)
    return np.array(rows, float).reshape(-1, WIDTH), np.array(sizes, float)


def features(own: np.ndarray) -> np.ndarray:
    """A line's own features, the mean of its neighbours', whether it comes first, and a constant."""
    if not len(own):
        return np.zeros((0, WIDTH + len(SHARED) + 2))
    part = own[:, SHARED]
    around = np.zeros_like(part)
    around[1:] += part[:-1]
    around[:-1] += part[1:]
    around /= np.maximum(1, np.r_[0, np.ones(len(own) - 1)] + np.r_[np.ones(len(own) - 1), 0])[:, None]
    first = np.zeros((len(own), 1))
    first[0] = 1
    return np.hstack((own, around, first, np.ones((len(own), 1))))


def marginals(emit: np.ndarray, move: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Forward-backward over padded chains: ``emit`` (chains, steps, 2), ``at`` marks steps that exist.

    Returns the marginals (chains, steps, 2) and the expected transitions, summed (2, 2).
    """
    n, steps, _ = emit.shape
    e, m = np.exp(emit - emit.max(axis=2, keepdims=True)), np.exp(move)
    fore = np.zeros_like(e)
    back = np.ones_like(e)
    fore[:, 0] = e[:, 0] / e[:, 0].sum(axis=1, keepdims=True)
    for t in range(1, steps):
        x = (fore[:, t - 1] @ m) * e[:, t]
        fore[:, t] = np.where(at[:, t, None], x / np.maximum(x.sum(axis=1, keepdims=True), 1e-300), 0)
    for t in range(steps - 2, -1, -1):
        x = (back[:, t + 1] * e[:, t + 1]) @ m.T
        back[:, t] = np.where(at[:, t + 1, None], x / x.sum(axis=1, keepdims=True), 1)
    both = fore * back
    marginal = both / np.maximum(both.sum(axis=2, keepdims=True), 1e-300)
    pair = fore[:, :-1, :, None] * m[None, None] * (e[:, 1:] * back[:, 1:])[:, :, None, :]
    pair = pair / np.maximum(pair.sum(axis=(2, 3), keepdims=True), 1e-300) * at[:, 1:, None, None]
    return marginal * at[:, :, None], pair.sum(axis=(0, 1))


class Field:
    """Weights of the labels' features (width, 2) and of the transitions (2, 2); label 1 is good."""

    def __init__(self, weights: np.ndarray, move: np.ndarray):
        self.weights, self.move = weights, move

    def quality(self, text: bytes | None) -> float:
        own, sizes = lines(text)
        if not len(own):
            return 0.0
        return self.mean(features(own), sizes)

    def mean(self, seen: np.ndarray, sizes: np.ndarray) -> float:
        """The marginals for good, weighted by the lengths of the lines."""
        got, _ = marginals((seen @ self.weights)[None], self.move, np.ones((1, len(seen)), bool))
        return float((got[0, :, 1] * sizes).sum() / sizes.sum())


def padded(chains: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(map(len, chains))
    x, at = np.zeros((len(chains), steps, chains[0].shape[1])), np.zeros((len(chains), steps), bool)
    for i, c in enumerate(chains):
        x[i, : len(c)], at[i, : len(c)] = c, True
    return x, at


def grouped(lengths: list[int]) -> list[list[int]]:
    """Chains of similar length together, within the bounds of a group."""
    out: list[list[int]] = []
    for i in np.argsort(lengths, kind="stable").tolist():
        if not out or len(out[-1]) >= GROUP_CHAINS or (len(out[-1]) + 1) * lengths[i] > GROUP_LINES:
            out.append([])
        out[-1].append(i)
    return out


def fit(chains: list[np.ndarray], good: np.ndarray, rounds: int = 60, rate: float = 0.15, ridge: float = 1e-3) -> Field:
    """Conditional likelihood by adaptive gradient steps over chains of similar length."""
    width = chains[0].shape[1]
    groups = [(padded([chains[i] for i in some]), good[some]) for some in grouped([len(c) for c in chains])]
    total = sum(len(c) for c in chains)
    w, move = np.zeros((width, 2)), np.zeros((2, 2))
    seen_w, seen_m = np.full_like(w, 1e-8), np.full_like(move, 1e-8)
    for _ in range(rounds):
        gw, gm = -ridge * w, -ridge * move
        for (x, at), y in groups:
            p, pair = marginals(x @ w, move, at)
            truth = np.zeros_like(p)
            truth[np.arange(len(y)), :, y] = at
            gw = gw + np.einsum("nsf,nsl->fl", x, truth - p) / total
            real = np.zeros((2, 2))
            np.add.at(real, (y, y), np.maximum(at.sum(axis=1) - 1, 0))
            gm = gm + (real - pair) / total
        seen_w += gw**2
        seen_m += gm**2
        w = w + rate * gw / np.sqrt(seen_w)
        move = move + rate * gm / np.sqrt(seen_m)
    return Field(w, move)


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        own = [lines(t.as_py()) for t in batch.column("text")]
        kind = pa.list_(pa.float64())
        yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([x.ravel() for x, _ in own], kind), pa.array([n for _, n in own], kind), batch.column("label")], names=["id", "x", "sizes", "y"])


def score(docs: DataFrame, labels: DataFrame, train: Column, id_col: str = "doc_id", text: str = "text", label: str = "quality", fit_rows: int = FIT_ROWS) -> DataFrame:
    """``(id, score)`` of every row of ``docs``; labels are learnt from where ``train`` holds."""
    few = stage(labels.where(train & F.col(label).isNotNull()).orderBy(F.xxhash64(id_col), id_col).limit(fit_rows), "crf-rows")
    some = labelled(docs.select(F.col(id_col), F.col(text).alias("text")), few, id_col, label)
    shown = some.select(F.col(id_col).cast("long").alias("id"), F.col("text").cast("binary").alias("text"), "label")
    got = shown.mapInArrow(_extract, "id long, x array<double>, sizes array<double>, y int").toPandas()
    got["x"] = got["x"].map(lambda v: features(np.array(v, float).reshape(-1, WIDTH)))
    got = got[got["x"].map(len) > 0].sort_values("id", kind="stable")
    field, weights = None, np.zeros(2)
    if got["y"].nunique() == 2:
        field = fit(got["x"].tolist(), got["y"].to_numpy(int))
        means = []
        for x, sizes in zip(got["x"], got["sizes"], strict=True):
            means.append(field.mean(x, np.array(sizes, float)))
        weights = logistic(_odds(np.array(means))[:, None], got["y"].to_numpy(float))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            q = np.array([field.quality(t.as_py()) if field else 0.5 for t in batch.column("text")], float)
            z = weights[0] + weights[1] * _odds(q)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(1 / (1 + np.exp(-np.clip(z, -30, 30))))], names=["id", "score"])

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("binary").alias("text"))
    return slim.mapInArrow(judge, "id long, score double")


def _odds(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-4, 1 - 1e-4)
    return np.log(p / (1 - p))
