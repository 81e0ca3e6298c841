"""Language identification by nearest centroid over TF-IDF character n-grams."""

from __future__ import annotations

import sys
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import tidy

#: Hashed n-gram features, n from 1 to 3.
FEATURES = 1 << 13
#: Rows the classifier is fitted on at most, shared evenly by the languages; centroids a language.
SAMPLE, CENTROIDS = 6000, 4
UNKNOWN = "und"
#: Code points that are counted at a time.
PIECE = 1 << 19


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1)


def _stretches(text: str) -> Iterator[np.ndarray]:
    """A lower-cased text's letters in pieces, every other stretch as one blank, with a blank at both ends."""
    before = False
    for at in range(0, max(1, len(text)), PIECE):
        c = np.frombuffer(text[at : at + PIECE].encode("utf-32-le", "surrogatepass"), np.uint32)
        letter = _letters()[c]
        keep = letter | np.append(before, letter[:-1])[: len(c)]
        before = bool(letter[-1:].any())
        ends = [32] * (at == 0), [32] * (at + PIECE >= len(text))
        yield np.concatenate([ends[0], np.where(letter, c, np.uint32(32))[keep], ends[1]]).astype(np.uint32)


def ngram_counts(text: str | None) -> np.ndarray | None:
    """Counts of hashed n-grams of the lower-cased letters, other stretches as one blank; None without a letter."""
    counts, letters, held = np.zeros(FEATURES, np.int64), False, np.zeros(0, np.uint32)
    for new in _stretches((text or "").lower()):
        letters |= bool((new != 32).any())
        c = np.concatenate([held, new])  # n-grams that end in the new piece
        one = c * np.uint32(0x9E3779B1)
        two = (one[:-1] ^ (one[:-1] >> np.uint32(15))) * np.uint32(0x85EBCA77) + one[1:]
        three = (two[:-1] ^ (two[:-1] >> np.uint32(13))) * np.uint32(0xC2B2AE3D) + one[2:]
        h = np.concatenate([one[len(held) :], two[max(0, len(held) - 1) :] * np.uint32(0x27D4EB2F), three * np.uint32(0x165667B1)])
        counts += np.bincount((h ^ (h >> np.uint32(16))) * np.uint32(0x9E3779B1) >> np.uint32(19), minlength=FEATURES)
        held = c[-2:]
    return counts if letters else None


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=-1, keepdims=True), 1e-12)


@dataclass
class CentroidModel:
    """Unit centroids, the language of each, the inverse document frequencies, and each centroid's rejection bound."""

    centroids: np.ndarray
    langs: list[str]
    idf: np.ndarray
    bound: np.ndarray

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        return _unit(np.log1p(counts.astype(np.float32)) * self.idf)

    def predict(self, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(centroid, cosine, rejected): rejected if farther from its centroid than almost all that it was fitted on."""
        near = self.vectors(counts) @ self.centroids.T
        best = near.argmax(axis=1)
        score = np.clip(near[np.arange(len(best)), best], 0, 1)
        return best, score, score < self.bound[best]


class SparseRows:
    """Unit TF-IDF vectors that hold only the n-grams a row has: about a hundredth of the dense ones."""

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], idf: np.ndarray):
        self.ends = np.cumsum([0, *(len(at) for at, _ in rows)])
        self.at = np.concatenate([at for at, _ in rows])
        value = np.log1p(np.concatenate([n for _, n in rows]).astype(np.float32)) * idf[self.at]
        norm = np.sqrt(np.add.reduceat(value * value, self.ends[:-1]))
        self.value = value / np.repeat(np.maximum(norm, 1e-12), np.diff(self.ends))

    def __len__(self) -> int:
        return len(self.ends) - 1

    def dense(self, i: int) -> np.ndarray:
        out = np.zeros(FEATURES, np.float32)
        span = slice(self.ends[i], self.ends[i + 1])
        out[self.at[span]] = self.value[span]
        return out

    def cosines(self, centroids: np.ndarray) -> np.ndarray:
        return np.stack([np.add.reduceat(self.value * c[self.at], self.ends[:-1]) for c in centroids], axis=1)

    def total(self, some: np.ndarray) -> np.ndarray:
        own = np.repeat(some, np.diff(self.ends))
        return np.bincount(self.at[own], self.value[own], FEATURES).astype(np.float32)


def fit(rows: list[tuple[str, np.ndarray, np.ndarray]], centroids: int = CENTROIDS, seed: int = 5, reject: float = 0.005) -> CentroidModel:
    """From (lang, n-grams, counts of each): spherical k-means within each language.

    ``reject``: share of its own rows a centroid rejects. Rows without n-grams teach nothing.
    """
    rows = [r for r in rows if len(r[1])]
    seen = np.zeros(FEATURES, np.int64)
    for _, at, _ in rows:
        seen[at] += 1
    idf = np.log((1 + len(rows)) / (1 + seen)).astype(np.float32) + 1
    if not rows:
        return CentroidModel(np.zeros((0, FEATURES), np.float32), [], idf, np.zeros(0))
    draw = np.random.default_rng(seed)
    found, names, bounds = [], [], []
    for lang in sorted({r[0] for r in rows}):
        x = SparseRows([(at, n) for own, at, n in rows if own == lang], idf)
        k = min(centroids, len(x))
        c = np.stack([x.dense(i) for i in draw.choice(len(x), k, replace=False)])
        for _ in range(12):
            own = x.cosines(c).argmax(axis=1)
            c = _unit(np.stack([x.total(own == j) if (own == j).any() else c[j] for j in range(k)]))
        near = x.cosines(c)
        own = near.argmax(axis=1)
        for j in range(k):
            if (own == j).any():
                found.append(c[j])
                names.append(lang)
                bounds.append(np.quantile(near[own == j, j], reject))
    return CentroidModel(np.stack(found).astype(np.float32), names, idf, np.array(bounds))


def learn(docs: DataFrame, usable: Column, sample: int = SAMPLE, centroids: int = CENTROIDS) -> CentroidModel:
    """Fit on at most about ``sample`` of the usable rows with a language, as many of each, drawn by a hash of doc_id.

    N-grams are counted where the rows lie; only the numbers and counts of those that a drawn row has come to the
    driver, never a text. Rows whose text or lang is null teach nothing; an empty table gives a model without languages.
    """
    rows = docs.where(usable & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = dict(rows.groupBy("lang").count().orderBy("lang").limit(sample).collect())  # one row a language
    if not counts:
        return fit([], centroids)
    each = max(1, sample // len(counts))
    share = F.lit(0.0)
    for lang, n in counts.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, each / n))).otherwise(share)
    spot = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 20)) / float(1 << 20)
    drawn = rows.where(spot < share).select("lang", "text", F.xxhash64("doc_id", F.lit(11)).alias("o"))

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 64):
                at, n = [], []
                for text in b.column(1)[lo : lo + 64]:
                    found = ngram_counts(text.as_py())
                    own = np.flatnonzero(found) if found is not None else np.zeros(0, np.int64)
                    at.append(own.astype("<u2").tobytes())
                    n.append(np.minimum(found[own], 2**32 - 1).astype("<u4").tobytes() if len(own) else b"")
                yield pa.RecordBatch.from_arrays([b.column(0)[lo : lo + 64], b.column(2)[lo : lo + 64], pa.array(at, pa.binary()), pa.array(n, pa.binary())], ["lang", "o", "at", "n"])

    found = drawn.mapInArrow(tidy(count), "lang string, o long, at binary, n binary").orderBy("o", "lang", "at", "n").limit(2 * sample)
    return fit([(r.lang, np.frombuffer(r.at, "<u2"), np.frombuffer(r.n, "<u4")) for r in found.toLocalIterator()], centroids)


def identify(docs: DataFrame, model: CentroidModel, batch: int = 256) -> DataFrame:
    """doc_id, lang_pred, score (cosine with the nearest centroid), rejected.

    lang_pred is the nearest centroid's language, or ``und`` (score 0, rejected) for null text and text without a
    letter, or if nothing was learned. Only the text is looked at, all of it; rows that share a doc_id are judged each.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # languages x centroids x FEATURES floats

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            n = b.num_rows
            lang, score, rejected = [UNKNOWN] * n, np.zeros(n), np.ones(n, bool)
            texts = b.column(1)
            for at in range(0, n if m.langs else 0, batch):
                counts = [ngram_counts(t) for t in texts[at : at + batch].to_pylist()]
                has = [i for i, c in enumerate(counts) if c is not None]
                if has:
                    best, s, r = m.predict(np.stack([counts[i] for i in has]))
                    for i, j in zip(has, best.tolist(), strict=True):
                        lang[at + i] = m.langs[j]
                    score[[at + i for i in has]], rejected[[at + i for i in has]] = s, r
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lang), pa.array(score, pa.float64()), pa.array(rejected)], ["doc_id", "lang_pred", "score", "rejected"])

    return docs.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, lang_pred string, score double, rejected boolean")
