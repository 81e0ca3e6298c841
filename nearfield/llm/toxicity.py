"""Toxicity by a classifier chain: linear models in a row, each also given the probabilities of those before it.

Later models are trained with out-of-fold probabilities of the earlier categories, so they meet at prediction what
they met in training.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .hashing import word_hashes
from .shared import plain, tidy

#: Hashed word features; labelled rows the chain is fitted on at most; folds; rows a feature needs in the sample.
FEATURES, SAMPLE, FOLDS, LEAST_ROWS = 1 << 18, 12_000, 4, 3
#: Least chi-square of a feature with a category for it to get a weight: most words of a small sample tell nothing.
LEAST_CHI = 12.0
#: Bytes of the word beginnings that are features beside the words, for words with endings.
BEGINNINGS = (4, 5, 6)
#: A-Z to a-z, every other ASCII character that is no letter or digit to a blank.
_FOLD = bytes(i + 32 if 65 <= i <= 90 else i if i >= 128 or chr(i).isalnum() else 32 for i in range(256))


def features(text: str | None) -> np.ndarray:
    """Sorted distinct feature numbers of a text's words and their beginnings, without case and punctuation."""
    h = word_hashes((text or "").encode("utf-8", "surrogatepass").translate(_FOLD), BEGINNINGS)
    return np.unique(h >> np.uint64(46)).astype(np.int32)


def _sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def _logit(p):
    p = np.clip(p, 1e-4, 1 - 1e-4)
    return np.log(p / (1 - p))


class WordRows:
    """The distinct features of each row end to end, without those of too few rows, numbered anew."""

    def __init__(self, rows: list[np.ndarray]):
        have = np.zeros(FEATURES, np.int32)
        for r in rows:
            have[r] += 1
        self.held = np.flatnonzero(have >= LEAST_ROWS)
        place = np.full(FEATURES, -1, np.int32)
        place[self.held] = np.arange(len(self.held))
        self.ends = np.cumsum([0, *(int((place[r] >= 0).sum()) for r in rows)])
        self.col = np.empty(self.ends[-1], np.int32)
        for r, start, end in zip(rows, self.ends[:-1], self.ends[1:], strict=True):
            new = place[r]
            self.col[start:end] = new[new >= 0]

    def spans(self, step: int = 1024) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(row, feature) of each entry, some rows at a time."""
        n = len(self.ends) - 1
        for lo in range(0, n, step):
            hi = min(n, lo + step)
            yield np.repeat(np.arange(lo, hi), np.diff(self.ends[lo : hi + 1])), self.col[self.ends[lo] : self.ends[hi]]


def telling(rows: WordRows, use: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Which features go with the label by more than chance, over the rows in use."""
    size, n, positive = len(rows.held), use.sum(), y[use].sum()
    have, both = np.zeros(size), np.zeros(size)
    for at, col in rows.spans():
        have += np.bincount(col[use[at]], minlength=size)
        both += np.bincount(col[(use & (y == 1))[at]], minlength=size)
    miss = both * n - have * positive
    return n * miss**2 / np.maximum(have * (n - have) * positive * (n - positive), 1e-9) >= LEAST_CHI


def fit_linear(rows: WordRows, use: np.ndarray, extra: np.ndarray, y: np.ndarray, l2: float = 2e-4, steps: int = 300, rate: float = 0.08):
    """Logistic regression on the rows in use, on their features and dense extra columns: (w, v, bias, z of all rows).

    Only features that tell by themselves get a weight.
    """
    own = telling(rows, use, y)
    place = np.cumsum(own) - 1
    size, total, n = int(own.sum()), len(y), use.sum()
    kept = [(at[k := own[col]], place[col[k]]) for at, col in rows.spans()]
    at, col = (np.concatenate([x[i] for x in kept] or [np.zeros(0)]).astype(np.intp) for i in (0, 1))
    del kept
    some, firsts = np.unique(at, return_index=True)
    order = np.argsort(col, kind="stable")
    down, starts = at[order], np.searchsorted(col[order], np.arange(size))  # every kept feature has an entry
    del at, order

    def scores(w: np.ndarray) -> np.ndarray:
        out = np.zeros(total)
        if size:
            out[some] = np.add.reduceat(w[col], firsts)
        return out

    w, v, bias = np.zeros(size), np.zeros(extra.shape[1]), float(_logit(y[use].mean()))
    moments = [np.zeros(size + len(v) + 1), np.zeros(size + len(v) + 1)]
    for t in range(1, steps + 1):
        z = scores(w) + extra @ v + bias
        g = np.where(use, _sigmoid(z) - y, 0) / n
        found = np.add.reduceat(g[down], starts) if size else w
        gradient = np.concatenate([found + l2 * w, extra.T @ g + l2 * v, [g.sum()]])
        moments[0] = 0.9 * moments[0] + 0.1 * gradient
        moments[1] = 0.999 * moments[1] + 0.001 * gradient**2
        step = rate * (moments[0] / (1 - 0.9**t)) / (np.sqrt(moments[1] / (1 - 0.999**t)) + 1e-9)
        w, v, bias = w - step[:size], v - step[size:-1], bias - step[-1]
    whole = np.zeros(len(rows.held))
    whole[own] = w
    return whole, v, bias, scores(w) + extra @ v + bias


@dataclass
class Chain:
    """Per category: weights of the hashed words, of the earlier categories' logits, the bias and the threshold."""

    categories: list[str]
    words: np.ndarray
    earlier: list[np.ndarray]
    bias: list[float]
    threshold: list[float]

    def probabilities(self, rows: list[np.ndarray]) -> np.ndarray:
        n = len(rows)
        at = np.repeat(np.arange(n), [len(r) for r in rows])
        col = np.concatenate(rows) if n else np.zeros(0, np.int32)
        out = np.zeros((n, len(self.categories)))
        for k in range(len(self.categories)):
            z = np.bincount(at, self.words[k][col], n) + self.bias[k]
            out[:, k] = _sigmoid(z + _logit(out[:, :k]) @ self.earlier[k])
        return out


def fit_chain(rows: list[np.ndarray], labels: np.ndarray, categories: list[str], fold: np.ndarray, folds: int = FOLDS) -> Chain:
    """``rows``: distinct feature numbers of each; ``labels``: rows x categories of 0 or 1; ``fold``: each row's fold.

    A category without both labels gets a constant. The threshold of each is the one of best F1 on out-of-fold
    probabilities.
    """
    n = len(rows)
    words = WordRows(rows)
    chain = Chain(categories, np.zeros((len(categories), FEATURES), np.float32), [], [], [])
    outside = np.zeros((n, 0))
    for k in range(len(categories)):
        y = labels[:, k].astype(float) if n else np.zeros(0)
        if n < 2 * folds or y.min() == y.max():
            chain.earlier.append(np.zeros(k))
            chain.bias.append(float(_logit(y.mean())) if n else -9.0)
            chain.threshold.append(0.5)
            outside = np.column_stack([outside, np.full(n, y.mean() if n else 0.0)])
            continue
        p = np.full(n, y.mean())
        for f in range(folds):
            test = fold == f
            if not test.any() or y[~test].min() == y[~test].max():
                continue
            z = fit_linear(words, ~test, _logit(outside), y)[3]
            p[test] = _sigmoid(z)[test]
        w, v, bias, _ = fit_linear(words, np.ones(n, bool), _logit(outside), y)
        chain.words[k, words.held] = w
        chain.earlier.append(v)
        chain.bias.append(float(bias))
        order = np.argsort(-p, kind="stable")
        hits = np.cumsum(y[order])
        f1 = 2 * hits / (np.arange(1, n + 1) + y.sum())
        best = int(f1.argmax())
        after = p[order[min(best + 1, n - 1)]]
        chain.threshold.append(float((p[order[best]] + after) / 2))
        outside = np.column_stack([outside, p])
    return chain


def learn(docs: DataFrame, labels: DataFrame, categories: dict[str, tuple[str, int]], sample: int = SAMPLE) -> Chain:
    """Fit the chain on at most about ``sample`` labelled documents, drawn by a hash of doc_id.

    ``categories``: name to (label column, the label that means it), in the chain's order. Rows with a null label or
    doc_id teach nothing; a document with unlike labels counts once for each.
    """
    names = list(categories)
    picks = [(F.col(c) == F.lit(v)).cast("int").alias(f"_y{i}") for i, (c, v) in enumerate(categories.values())]
    known = labels.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("_nf_id"), *picks).dropna().distinct()
    n = known.count()
    spot = F.xxhash64("_nf_id", F.lit(7))
    drawn = known.where(F.pmod(spot, F.lit(1 << 24)) < F.lit(int((1 << 24) * min(1.0, sample / max(1, n)))))
    rows = drawn.join(docs.select("doc_id", plain("text").alias("text")), F.col("_nf_id") == F.col("doc_id"))
    width = len(names)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [features(t).tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.binary()), *(b.column(2 + i) for i in range(width))], ["spot", "f", *(f"_y{i}" for i in range(width))])

    ys = [f"_y{i}" for i in range(width)]
    found = rows.select(spot.alias("spot"), "text", *ys).mapInArrow(tidy(run), "spot long, f binary, " + ", ".join(f"{y} int" for y in ys))
    got = [(r.spot, bytes(r.f), *r[2:]) for r in found.toLocalIterator()]
    got.sort()
    y = np.array([r[2:] for r in got], np.int8).reshape(len(got), width)
    fold = np.array([(r[0] >> 24) % FOLDS for r in got])
    return fit_chain([np.frombuffer(r[1], np.int32) for r in got], y, names, fold)


def predict(docs: DataFrame, chain: Chain, batch: int = 512) -> DataFrame:
    """``docs`` with p_<category> and is_<category> for each category of the chain, in its order.

    The whole text counts; null text is text without words. Rows that share a doc_id are judged each. Columns of the
    input that have an output's name are replaced.
    """
    shared = docs.sparkSession.sparkContext.broadcast(chain)  # categories x FEATURES floats
    new = [f"p_{c}" for c in chain.categories] + [f"is_{c}" for c in chain.categories]
    kept = [c for c in docs.columns if c not in new]
    rows = docs.select(*kept)
    at, schema = kept.index("text"), StructType(list(rows.schema.fields))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        for b in batches:
            parts = [c.probabilities([features(t) for t in b.column(at)[i : i + batch].to_pylist()]) for i in range(0, b.num_rows, batch)]
            p = np.concatenate(parts) if parts else np.zeros((0, len(c.categories)))
            columns = [pa.array(p[:, k]) for k in range(p.shape[1])] + [pa.array(p[:, k] >= c.threshold[k]) for k in range(p.shape[1])]
            yield pa.RecordBatch.from_arrays([*b.columns, *columns], [*kept, *new])

    for name in new:
        schema = schema.add(name, "double" if name.startswith("p_") else "boolean")
    return rows.mapInArrow(tidy(run), schema)
