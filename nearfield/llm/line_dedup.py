"""Line dedup: lines that several documents share stay only in the document with the largest doc_id."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import ASCII_SPACE, LEAST_LONG, cut, tidy

_WS = ASCII_SPACE.encode()


def line_key(line: bytes) -> bytes:
    """A line without white space at its ends, A-Z in lower case."""
    return line.strip(_WS).lower()


def _digest(line: bytes, least: int) -> bytes | None:
    """128 bits of a line's key, if the key has so many code points."""
    key = line_key(line)
    if len(key) < least or not key.isascii() and len(key.decode("utf-8", "replace")) < least:
        return None
    return xxhash.xxh3_128_digest(key)


def line_digests(docs: DataFrame, least: int) -> DataFrame:
    """(doc, h1, h2): the distinct long keys of each row, as 128-bit hashes; null doc_id as the least long."""

    def found(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, parts = [], []
            for d, text in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), strict=True):
                own = {h for line in text.split(b"\n") if len(line) >= least and (h := _digest(line, least))}
                ids.append(np.full(len(own), d))
                parts.extend(own)
            h = np.frombuffer(b"".join(parts), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(ids) if ids else [], pa.int64()), pa.array(h[:, 0]), pa.array(h[:, 1])], ["doc", "h1", "h2"])

    rows = docs.select(F.coalesce("doc_id", F.lit(LEAST_LONG)).alias("doc_id"), "text").where(F.length("text") >= least)
    return rows.mapInArrow(tidy(found), "doc long, h1 long, h2 long")


def dedup_lines(docs: DataFrame, least: int = 20, documents: int = 3) -> DataFrame:
    """``docs`` with repeated lines gone from ``text``, and n_lines (before), n_dropped.

    A line's key is the line stripped of ASCII white space with A-Z lower-cased. Keys of at least ``least`` code
    points in at least ``documents`` documents lose all their lines but those of the rows with the largest doc_id
    holding it; lines without such a key stay, joined by newlines. Rows that share a doc_id are one document, and so
    are those without one, which come below all others. Null text stays null and counts as one empty line. Columns of the input named
    n_lines or n_dropped are replaced; all others are kept.

    Distinct documents are counted in two steps (a line's documents, then their number, combined before it is
    shuffled), and each row of a line's documents finds the line's one count, so a line of a third of all documents is
    no hot key for the count, and one that the join may split.
    """
    once = line_digests(docs, least).distinct()
    counts = once.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"), F.max("doc").alias("keeper"))
    # cut, so that the join below deals both sides out anew and Spark may split a common line's rows
    shared = cut(counts.where(F.col("n") >= documents).select(F.col("h1").alias("s1"), F.col("h2").alias("s2"), "keeper"))
    lines = line_digests(docs, least)
    lost = lines.join(shared, (F.col("h1") == F.col("s1")) & (F.col("h2") == F.col("s2"))).where(F.col("doc") != F.col("keeper"))
    lost = lost.groupBy("doc").agg(F.collect_set(F.struct("h1", "h2")).alias("_nf_lost"))
    kept = [c for c in docs.columns if c not in ("n_lines", "n_dropped", "_nf_lost", "_nf_doc")]
    rows = docs.select(*kept, F.coalesce("doc_id", F.lit(LEAST_LONG)).alias("_nf_doc"))
    rows = rows.join(lost, F.col("_nf_doc") == F.col("doc"), "left").select(*kept, "_nf_lost")
    at, schema = kept.index("text"), rows.select(*kept).schema

    def drop(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, gone = b.column(at).cast(pa.binary()).to_pylist(), b.column(len(kept))
            ends = np.cumsum([0, *(n or 0 for n in gone.value_lengths().to_pylist())])
            flat = gone.flatten()
            pairs = np.empty((len(flat), 2), np.int64)
            if len(flat):
                pairs[:, 0], pairs[:, 1] = flat.flatten()
            n_lines, n_dropped = [], []
            for i, text in enumerate(texts):
                n_lines.append(1 if text is None else text.count(b"\n") + 1)
                n_dropped.append(0)
                if ends[i] < ends[i + 1]:
                    bad = {p.tobytes() for p in pairs[ends[i] : ends[i + 1]]}
                    lines = text.split(b"\n")
                    left = [x for x in lines if len(x) < least or _digest(x, least) not in bad]
                    n_dropped[-1] = len(lines) - len(left)
                    texts[i] = b"\n".join(left)
            columns = [b.column(i) for i in range(len(kept))]
            columns[at] = pa.array(texts, pa.binary()).cast(pa.string())
            columns += [pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, [*kept, "n_lines", "n_dropped"])

    return rows.mapInArrow(tidy(drop), schema.add("n_lines", "long").add("n_dropped", "long"))
