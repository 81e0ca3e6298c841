"""N-gram Jaccard join with a token-group matrix.

Similar documents are put into one part by signature bands. Within a part, documents lie in small groups; a matrix
holds for each shingle the groups whose union has it. A document's overlap with a group's union bounds its overlap
with every member, so only groups whose bound can reach the wanted similarity are opened and their members compared
by their exact sets. Links are followed from document to document until each part falls into linked components.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .fingerprints import equal_sets, set_table
from .hashing import shingle_set
from .shared import cut, plain, tidy

#: Documents in a group of the matrix.
GROUP = 32
#: A part is dealt in pairs of blocks of so many documents, but in so many blocks at most; yet no block has more than
#: MOST_DOCUMENTS documents or about MOST_SHINGLES shingles.
BLOCK, BLOCKS, MOST_DOCUMENTS, MOST_SHINGLES = 128, 64, 6000, 1 << 22


class TokenGroupMatrix:
    """Shingle sets in groups of similar ones; ``reach(i)`` gives the open documents linked with document i.

    ``percent``: documents link when 100 * intersection >= percent * union, in integers.
    """

    def __init__(self, sets: list[np.ndarray], percent: int, group: int = GROUP):
        self.percent, self.sizes = percent, np.array([s.size for s in sets], np.int64)
        self.open = np.ones(len(sets), bool)
        self.sets = sets
        self.group = group
        self._build(np.array(sorted(range(len(sets)), key=lambda i: sets[i][:4].tobytes()), np.int64))

    def _build(self, members: np.ndarray) -> None:
        """Lay out the open documents anew: by group the union of tokens, by token its groups and its documents."""
        self.members, self.left = members, len(members)
        own = np.arange(len(members))
        self.group_of = own // self.group
        self.n_groups = int(self.group_of[-1]) + 1 if len(members) else 0
        flat = np.concatenate([self.sets[i] for i in members]) if len(members) else np.zeros(0, np.uint64)
        who = np.repeat(own, self.sizes[members])
        order = np.argsort(flat, kind="stable")
        flat, self.who = flat[order], who[order]
        self.tokens, self.at = np.unique(flat, return_index=True)
        self.at = np.append(self.at, len(flat))
        groups = self.group_of[self.who]
        new = np.ones(len(flat), bool)
        new[1:] = (flat[1:] != flat[:-1]) | (groups[1:] != groups[:-1])
        self.union = groups[new]
        self.union_at = np.append(0, np.cumsum(new))[self.at]
        self.least = np.minimum.reduceat(self.sizes[members], np.arange(0, len(members), self.group)) if len(members) else np.zeros(0)
        self.most = np.maximum.reduceat(self.sizes[members], np.arange(0, len(members), self.group)) if len(members) else np.zeros(0)

    def close(self, documents: list[int]) -> None:
        self.open[documents] = False
        self.left -= len(documents)
        if self.left < len(self.members) // 2 and len(self.members) > 2 * self.group:
            self._build(self.members[self.open[self.members]])

    def reach(self, i: int, only: np.ndarray | None = None) -> list[int]:
        """Open documents that link with document i; of ``only`` (a mask), if given."""
        found = self.linked(i)[0]
        found = found[self.open[found]]
        return (found if only is None else found[only[found]]).tolist()

    def linked(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Every laid out document that links with document i, and how many shingles each shares with it."""
        none = np.zeros(0, np.int64), np.zeros(0, np.int64)
        s, n, p = self.sets[i], int(self.sizes[i]), self.percent
        if not n or not len(self.members):
            return none
        place = np.searchsorted(self.tokens, s)
        place[place == len(self.tokens)] = 0
        place = place[self.tokens[place] == s]
        if not place.size:
            return none
        need = (self.most * 0 + -(-n * p // 100)).astype(np.int64)  # at least p percent of the larger set is common
        need = np.maximum(need, -(-self.least * p // 100)).astype(np.int64)
        spans = self.union_at[place + 1] - self.union_at[place]
        rare = np.argsort(spans, kind="stable")
        miss = n - int(need.min()) + 1 + (place.size - n)  # tokens found nowhere count as missed
        if miss <= 0:
            return none
        some = _ranges(self.union_at[place[rare[:miss]]], spans[rare[:miss]])
        seen = np.zeros(self.n_groups, bool)
        seen[self.union[some]] = True  # a group without any of the rarest cannot have enough of the rest
        if not seen.any():
            return none
        bound = np.bincount(self.union[_ranges(self.union_at[place], spans)], minlength=self.n_groups)
        wide = (self.most * 100 >= n * p) & (self.least * p <= n * 100)
        opened = seen & wide & (bound >= need)
        if not opened.any():
            return none
        spans = self.at[place + 1] - self.at[place]
        who = self.who[_ranges(self.at[place], spans)]
        who = who[opened[self.group_of[who]]]
        common = np.bincount(who, minlength=len(self.members))
        sizes = self.sizes[self.members]
        good = (100 * common >= p * (n + sizes - common)) & (common > 0)
        good &= self.members != i
        return self.members[good], common[good]


def _ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """All indices of the given spans, in order."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lengths)
    return np.arange(total) - np.repeat(ends - lengths - starts, lengths)


def spanning_links(sets: list[np.ndarray], percent: int, side: np.ndarray | None = None, weights: np.ndarray | None = None) -> tuple[list[tuple[int, int]], np.ndarray]:
    """(links that connect all that links connect, number of links of each document).

    Each document reached is linked to the one that reached it. With ``weights`` every document's links are counted too,
    a link to a document as often as its weight; without, the numbers are zeros and what is reached is no longer
    searched. ``side`` (0 or 1): only links between the sides are sought; those within a side are other tasks'.
    """
    matrix = TokenGroupMatrix(sets, percent)
    out: list[tuple[int, int]] = []
    counts = np.zeros(len(sets), np.int64)
    if side is not None and (side == side[:1]).all():
        return out, counts

    def close(documents: list[int]) -> None:
        if weights is None:
            matrix.close(documents)
        else:
            matrix.open[documents] = False  # but stay laid out

    for root in range(len(sets)):
        if not matrix.open[root]:
            continue
        close([root])
        front = [root]
        while front:
            i = front.pop()
            if weights is None:
                found = matrix.reach(i, None if side is None else side != side[i])
            else:
                near = matrix.linked(i)[0]
                near = near if side is None else near[side[near] != side[i]]
                counts[i] = weights[near].sum()
                found = near[matrix.open[near]].tolist()
            if found:
                close(found)
                out.extend((i, j) for j in found)
                front.extend(found)
    return out, counts


def all_links(sets: list[np.ndarray], percent: int, side: np.ndarray | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(i, linked documents, shingles shared with each): every link once, at the document that comes first.

    With ``side`` links between the sides only, each at the document of side 0.
    """
    matrix = TokenGroupMatrix(sets, percent)
    for i in range(len(sets)) if side is None else np.flatnonzero(side == 0).tolist():
        found, common = matrix.linked(i)
        mine = found > i if side is None else side[found] == 1
        if mine.any():
            yield i, found[mine], common[mine]


def bands_for(percent: int) -> tuple[int, int]:
    """(rows, bands) with which a pair at the threshold shares no band once in 10^9 pairs."""
    rows = 6 if percent >= 88 else 5
    t = percent / 100
    return rows, ceil(np.log(1e-9) / np.log1p(-(t**rows)))


def deal(sets: DataFrame, block: int = BLOCK) -> DataFrame:
    """(node, part, x, y, side) from (doc_id, n_shingles, bands): parts are what bands connect, and tasks (part, x, y)
    pairs of its blocks.

    Of a part of up to ``block`` documents x = y = 0. Larger ones fall into blocks by hash; task x < y holds both blocks
    as sides 0 and 1, task x = y one block. A family of many copies so becomes many small tasks; that each document
    lies in as many tasks as there are blocks is bounded by BLOCKS for all but the largest families.
    """
    bands = sets.select("doc_id", F.explode("bands").alias("band"))
    first = bands.groupBy("band").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select(F.col("band").alias("k"), "first")
    near = bands.join(first, F.col("band") == F.col("k")).select(F.col("first").alias("a"), F.col("doc_id").alias("b"))
    parts = connected_components(near)
    sized = cut(parts.join(sets.select("doc_id", "n_shingles"), F.col("node") == F.col("doc_id")).select("node", "component", "n_shingles"))
    counts = sized.groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.sum("n_shingles").alias("s")).withColumnRenamed("component", "part")
    blocks = F.greatest(F.least(F.ceil(F.col("n") / block), F.lit(BLOCKS)), F.ceil(F.col("n") / MOST_DOCUMENTS), F.ceil(F.col("s") / MOST_SHINGLES))
    counts = counts.select("part", blocks.cast("long").alias("blocks"))
    dealt = sized.join(counts, F.col("component") == F.col("part")).withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))
    dealt = dealt.select("node", "part", "own", other.alias("other"))
    return dealt.select("node", "part", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), (F.col("own") > F.col("other")).cast("int").alias("side"))


def by_task(work: DataFrame, search: Callable[[list[tuple]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """``search`` over the rows (side, doc_id, text, whether sides matter, what else ``work`` has) of each task (part, x, y)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, rows = None, []
        for b in batches:
            for part, x, y, side, d, text, *more in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if (part, x, y) != now:
                    yield from search(rows)
                    now, rows = (part, x, y), []
                rows.append((side, d, text, x != y, *more))
        yield from search(rows)

    return work.repartition("part", "x", "y").sortWithinPartitions("part", "x", "y").mapInArrow(tidy(run), schema)


def jaccard_components(docs: DataFrame, words: int, percent: int, block: int = BLOCK, links: bool = True) -> DataFrame:
    """(doc_id, n_shingles, component_id, n_links) of a self-join by Jaccard similarity of word shingles.

    Documents link when 100 * intersection >= percent * union of their distinct shingles (A-Z lower-cased words; with
    fewer words the whole sequence is one shingle). component_id is the least doc_id reachable by links; n_links is
    the number of links of the document with others, equal sets among them; ``links=False`` leaves it out, which is
    cheaper: components need a spanning forest only. Documents without words, or null text,
    link with nothing. Rows without doc_id link with nothing either and come back one by one, with a null
    component_id; rows that share a doc_id are one document that has the links of
    all its texts (added up in n_links), and the least component of them. Other columns are ignored.

    Equal sets are one class before anything is compared, however many copies there are. A pair of sets at the
    threshold meets in no band once in 10^9 pairs (as rare as a collision of the 64-bit shingle hashes); above it
    more seldom. Parts over ``block`` documents are dealt in pairs of blocks, see ``deal``.
    """
    import xxhash

    every = cut(set_table(docs, words, *bands_for(percent)))
    table = every.where("doc_id is not null")
    some = table.where("n_shingles > 0")
    sets = equal_sets(some)
    dealt = deal(sets.where("least = class_id").select(F.col("class_id").alias("doc_id"), "n_shingles", "bands"), block)
    texts = docs.where(F.col("doc_id").isNotNull()).select("doc_id", plain("text").alias("text"))
    work = texts.join(dealt, F.col("doc_id") == F.col("node")).select("part", "x", "y", "side", "doc_id", "text")
    if links:
        once = sets.where("least = class_id")
        own = once.groupBy("class_id").agg(F.collect_set(F.struct("s1", "s2", "copies")).alias("classes"))  # one, or as many as a doc_id has texts
        work = work.join(own, F.col("doc_id") == F.col("class_id")).select(*work.columns, "classes")

    def search(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows.sort(key=lambda r: (r[1], r[2]))
        sets = [shingle_set(r[2], words) for r in rows]
        side = np.array([r[0] for r in rows]) if rows and rows[0][3] else None
        keys, weights = [], None
        if links:
            left = {(r[1], c["s1"], c["s2"]): c["copies"] for r in rows for c in r[4]}
            keys = [tuple(np.frombuffer(xxhash.xxh3_128_digest(x), np.int64).tolist()) for x in sets]
            weights = np.array([left.pop((r[1], *k), 0) for r, k in zip(rows, keys, strict=True)], np.int64)  # each class once
        found, counts = spanning_links(sets, percent, side, weights)
        yield _links([(rows[i][1], rows[j][1], None, None, None) for i, j in found])
        if links:
            yield _links([(None, None, *keys[i], int(counts[i])) for i in np.flatnonzero((counts > 0) & (weights > 0))])

    found = cut(by_task(work, search, "a long, b long, s1 long, s2 long, n long"))
    linked = connected_components(found.where("a <> b").select("a", "b"))
    component = sets.select("s1", "s2", "ids", "class_id", "copies").join(linked, F.col("class_id") == F.col("node"), "left")
    columns = [F.min(F.coalesce("component", "class_id")).alias("component_id")]
    if links:
        counts = found.where("n is not null").groupBy(F.col("s1").alias("t1"), F.col("s2").alias("t2")).agg(F.sum("n").alias("n"))
        component = component.join(counts, (F.col("s1") == F.col("t1")) & (F.col("s2") == F.col("t2")), "left")
        columns.append(F.sum(F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    component = component.withColumn("doc_id", F.explode("ids")).groupBy("doc_id").agg(*columns)
    sizes = table.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")).withColumnRenamed("doc_id", "_id")
    out = sizes.join(component, F.col("_id") == F.col("doc_id"), "left")
    out = out.select(F.col("_id").alias("doc_id"), "n_shingles", F.coalesce("component_id", "_id").alias("component_id"), *["n_links"] * links)
    if links:
        out = out.withColumn("n_links", F.coalesce("n_links", F.lit(0)).cast("long"))
    lone = every.where("doc_id is null").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"), *[F.lit(0).cast("long").alias("n_links")] * links)
    return out.union(lone)


def _links(found: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*found, strict=True)) or [()] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["a", "b", "s1", "s2", "n"])


def drop_near_copies(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one document of each linked group left: that with the least doc_id. Rows without doc_id stay."""
    gone = jaccard_components(docs, words, percent, links=False).where("component_id <> doc_id").select(F.col("doc_id").alias("_nf_gone"))
    return docs.join(gone, F.col("doc_id") == F.col("_nf_gone"), "left_anti")
