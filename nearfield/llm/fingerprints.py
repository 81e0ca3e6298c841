"""Document fingerprints: MinHash signatures of word shingles, and near-duplicate pairs from their bands."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hashing import MinHasher, shingle_set
from .shared import LEAST_LONG, cut, plain, tidy

WORDS, SIZE = 5, 128
#: Documents about that share a range of doc_ids when each finds the next one, and the most ranges.
RANGE_ROWS, MOST_RANGES = 4096, 20_000


@lru_cache(maxsize=4)
def hasher(size: int) -> MinHasher:
    return MinHasher(size)


def fingerprint(text: str | None, words: int = WORDS, size: int = SIZE) -> np.ndarray:
    """uint16 values: the upper half of each least hash. Texts without words have all ones."""
    return (hasher(size).signature(shingle_set(text, words)) >> np.uint32(16)).astype(np.uint16)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Share of equal values: an estimate of the Jaccard similarity of two shingle sets."""
    return float((a == b).mean())


def to_hex(f: np.ndarray) -> str:
    return f.astype(">u2").tobytes().hex()


def add_fingerprints(docs: DataFrame, words: int = WORDS, size: int = SIZE) -> DataFrame:
    """(doc_id, fingerprint) of every whole text: 4 hex digits for each hash. Null text is empty text."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [to_hex(fingerprint(t, words, size)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.string())], ["doc_id", "fingerprint"])

    return docs.select("doc_id", plain("text").alias("text")).mapInArrow(tidy(run), "doc_id long, fingerprint string")


def with_next(docs: DataFrame) -> DataFrame:
    """(range, place, doc_id, text): rows in descending doc_id order (null last), cut into ranges that overlap by one row.

    Ranges hold about equally many doc_ids. The first row of each is also the last of the range before it, and the
    very first row the last of the last range, so every row meets its next one in its range by one shuffle of the
    texts. Within a range, place 0 marks own rows and 1 the row that only follows. Rows that share a doc_id lie in
    one range, by the text's hash.
    """
    key = F.coalesce("doc_id", F.lit(LEAST_LONG))
    rows = docs.select(key.alias("key"), "doc_id", plain("text").alias("text"))
    n = rows.count()
    ranges = max(1, min(MOST_RANGES, n // RANGE_ROWS))
    ends: list[int] = []
    if ranges > 1:
        shares = [i / ranges for i in range(1, ranges)]
        ends = sorted(set(rows.agg(F.percentile_approx("key", shares, 20 * ranges).alias("p")).first().p))
    number = F.lit(0)
    if ends:  # range 0 is that of the largest keys
        bounds = F.array(*[F.lit(e) for e in ends])
        number = F.lit(len(ends)) - F.size(F.filter(bounds, lambda e: e < F.col("key"))) if len(ends) < 64 else number_by_search(ends)
    rows = rows.withColumn("range", number.cast("int"))
    tie = F.xxhash64("text")
    firsts = rows.groupBy("range").agg(F.max(F.struct("key", tie.alias("tie"))).alias("top")).orderBy("range").collect()  # one small row a range
    before = {firsts[i].range: firsts[i - 1].range for i in range(len(firsts))}
    if firsts:
        before[firsts[0].range] = firsts[-1].range
    heads = docs.sparkSession.createDataFrame([(f.range, f.top.key, f.top.tie, before[f.range]) for f in firsts], "r int, k long, h long, before int")
    same = (F.col("range") == F.col("r")) & (F.col("key") == F.col("k")) & (tie == F.col("h"))
    copies = rows.join(F.broadcast(heads), same).dropDuplicates(["range"]).select(F.col("before").alias("range"), F.lit(1).alias("place"), "key", "doc_id", "text")
    return rows.select("range", F.lit(0).alias("place"), "key", "doc_id", "text").unionByName(copies)


def number_by_search(ends: list[int]):
    """How many of the sorted ends are at least the key, by a search of fixed depth in a literal array."""
    tree = F.array(*[F.lit(e) for e in ends])
    low, high = F.lit(0), F.lit(len(ends))
    low = F.aggregate(
        F.sequence(F.lit(1), F.lit(len(ends).bit_length())),
        F.struct(low.alias("a"), high.alias("b")),
        lambda s, _: F.when(s.a >= s.b, s).when(
            F.element_at(tree, (F.floor((s.a + s.b) / 2) + 1).cast("int")) < F.col("key"),
            F.struct((F.floor((s.a + s.b) / 2) + 1).cast("int").alias("a"), s.b.alias("b")),
        ).otherwise(F.struct(s.a.alias("a"), F.floor((s.a + s.b) / 2).cast("int").alias("b"))),
        lambda s: s.a,
    )
    return F.lit(len(ends)) - low


def edited_fingerprints(docs: DataFrame, words: int = WORDS, size: int = SIZE) -> DataFrame:
    """Each text's fingerprint beside that of an edited text and of the next document's.

    The edited text has its last floor(n / 3) code points replaced by the first as many (or all) of the next document
    in descending doc_id order; after the last comes the first. Null doc_ids come last, null text is empty text; a
    single document is its own next. Returns doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint,
    near_edited, near_next. Other columns are ignored.
    """
    import hashlib

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            out: list[tuple] = []
            for r, place, d, text in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                own = fingerprint(text, words, size)
                if held is not None and held[0] == r:
                    _, d0, t0, f0 = held
                    n = len(t0)
                    cut_at = n - n // 3
                    edited = t0[:cut_at] + text[: n // 3]
                    fe = fingerprint(edited, words, size)
                    sha = hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest()
                    out.append((d0, n, sha, to_hex(f0), to_hex(fe), likeness(f0, fe), likeness(f0, own)))
                held = None if place else (r, d, text, own)
            columns = list(zip(*out, strict=True)) or [()] * 7
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    rows = with_next(docs).repartition("range")
    rows = rows.sortWithinPartitions("range", "place", F.desc("key"), F.desc(F.xxhash64("text")), "text")
    return rows.select("range", "place", "doc_id", "text").mapInArrow(
        tidy(run), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    )


def near_pairs(docs: DataFrame, at_least: float = 0.8, words: int = WORDS, rows: int = 5, bands: int = 52, block: int = 128) -> DataFrame:
    """Near-duplicate pairs (a, b, jaccard) between class representatives: bands joined in Spark, Jaccard verified.

    Equal shingle sets are one class, named by its least doc_id; ``near_classes`` gives the membership. Of documents that
    bands connect, all pairs over ``at_least`` by exact Jaccard are returned with a < b, each once: a token-group matrix
    finds them in pairs of blocks, see ``jaccard_groups.deal``, however large a family is. A pair that shares no band and
    that no chain of bands connects is missed; at 0.8 that is one in 10^9 with the 52 bands of 5.
    """
    from .jaccard_groups import all_links, by_task, deal

    sets = equal_sets(cut(set_table(docs.where(F.col("doc_id").isNotNull()), words, rows, bands)))
    dealt = deal(sets.where("least = class_id").select(F.col("class_id").alias("doc_id"), "n_shingles", "bands"), block)
    work = docs.where(F.col("doc_id").isNotNull()).select("doc_id", plain("text").alias("text")).join(dealt, F.col("doc_id") == F.col("node"))
    percent = max(0, int(100 * at_least - 1e-9))  # not above at_least, which decides

    def search(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows.sort(key=lambda r: (r[1], r[2]))
        ids = np.array([r[1] for r in rows], np.int64)
        sets = [shingle_set(r[2], words) for r in rows]
        sizes = np.array([s.size for s in sets], np.int64)
        side = np.array([r[0] for r in rows]) if rows and rows[0][3] else None
        for i, found, common in all_links(sets, percent, side):
            j = common / (sizes[i] + sizes[found] - common)
            good = (j >= at_least) & (ids[found] != ids[i])
            a, b = np.minimum(ids[i], ids[found[good]]), np.maximum(ids[i], ids[found[good]])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(j[good], pa.float64())], ["a", "b", "jaccard"])

    found = by_task(work.select("part", "x", "y", "side", "doc_id", "text"), search, "a long, b long, jaccard double")
    return found.groupBy("a", "b").agg(F.max("jaccard").alias("jaccard"))  # rows that share a doc_id may meet twice


def near_classes(docs: DataFrame, words: int, rows: int, bands: int) -> DataFrame:
    """(doc_id, class_id, n_shingles, bands): class_id is the least doc_id with an equal shingle set; see ``set_table``."""
    sets = equal_sets(cut(set_table(docs.where(F.col("doc_id").isNotNull()), words, rows, bands)))
    return sets.select(F.explode("ids").alias("doc_id"), "class_id", "n_shingles", "bands")


#: Parts that the documents of one set are gathered in at least, and documents in a part of the largest classes, about.
PARTS, PART_DOCUMENTS = 16, 100_000


def equal_sets(table: DataFrame) -> DataFrame:
    """(s1, s2, ids, least, class_id, copies, n_shingles, bands): documents of equal sets in parts, beside the least
    doc_id and the number of rows of the whole class.

    ``table``: see ``set_table``, cut. Copies are gathered by set and part, so a class of a third of all documents is
    spread; what meets by the set alone are its parts, few rows each with many ids.
    """
    parts = max(PARTS, -(-table.count() // PART_DOCUMENTS))
    part = F.pmod(F.xxhash64("doc_id"), F.lit(parts))
    lists = table.groupBy("s1", "s2", part.alias("p")).agg(
        F.collect_list("doc_id").alias("ids"), F.min("doc_id").alias("least"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands")
    )
    whole = lists.groupBy(F.col("s1").alias("t1"), F.col("s2").alias("t2")).agg(F.min("least").alias("class_id"), F.sum(F.size("ids")).alias("copies"))
    both = lists.join(whole, (F.col("s1") == F.col("t1")) & (F.col("s2") == F.col("t2")))
    return both.select("s1", "s2", "ids", "least", "class_id", "copies", "n_shingles", "bands")


def set_table(docs: DataFrame, words: int, rows: int, bands: int) -> DataFrame:
    """(doc_id, n_shingles, s1, s2, bands): size and 128-bit hash of each row's shingle set, and its signature's band keys.

    Rows without words have no bands and a set hash of their own null kind.
    """
    import xxhash

    from .hashing import band_keys

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = hasher(rows * bands)
        for b in batches:
            n, h, keys = [], [], []
            for text in b.column(1).to_pylist():
                s = shingle_set(text, words)
                n.append(s.size)
                h.append(xxhash.xxh3_128_digest(s))
                keys.append(band_keys(own.signature(s), rows) if s.size else np.zeros(0, np.int64))
            ends = pa.array(np.cumsum([0, *(k.size for k in keys)]), pa.int32())
            flat = pa.array(np.concatenate(keys) if keys else [], pa.int64())
            h = np.frombuffer(b"".join(h), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(h[:, 0]), pa.array(h[:, 1]), pa.ListArray.from_arrays(ends, flat)], ["doc_id", "n_shingles", "s1", "s2", "bands"])

    return docs.select("doc_id", plain("text").alias("text")).mapInArrow(tidy(run), "doc_id long, n_shingles long, s1 long, s2 long, bands array<long>")


__all__ = ["add_fingerprints", "edited_fingerprints", "fingerprint", "likeness", "near_classes", "near_pairs", "set_table", "with_next"]
