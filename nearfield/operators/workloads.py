"""The experiments' matrices, built from the given tables by deterministic expressions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pandas.util import hash_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.elements import ElementModel
from ..sources.tables import cut, table
from .lattice import Box, atoms, box_of, neighbours

# ---- block-diagonal cliques: every function has a closed form


def cliques(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row, col, m): customers of one nation and segment, all pairs of a clique, with its size."""
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    size = c.groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("m"))
    c = c.join(size, ["c_nationkey", "c_mktsegment"])
    other = c.select(F.col("c_custkey").alias("col"), "c_nationkey", "c_mktsegment")
    return c.join(other, ["c_nationkey", "c_mktsegment"]).select(F.col("c_custkey").alias("row"), "col", "m")


def clique_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(member, clique, m): customers with the least id and the size of their clique."""
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    by = c.groupBy("c_nationkey", "c_mktsegment").agg(F.min("c_custkey").alias("clique"), F.count(F.lit(1)).alias("m"))
    return cut(c.join(by, ["c_nationkey", "c_mktsegment"]).select(F.col("c_custkey").alias("member"), "clique", "m"))


def clique_matrix(spark: SparkSession, sf_dir: str, a: float, b: float) -> DataFrame:
    """a I + (b / m) J on each clique."""
    on = (F.col("row") == F.col("col")).cast("double")
    return cliques(spark, sf_dir).select("row", "col", (a * on + b / F.col("m")).alias("val"))


def clique_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row, col, h, s) with H = -0.4 I + 0.9 J / m and S = I + 0.5 J / m: one empty state a clique at mu = 0."""
    on = (F.col("row") == F.col("col")).cast("double")
    return cliques(spark, sf_dir).select("row", "col", (-0.4 * on + 0.9 / F.col("m")).alias("h"), (on + 0.5 / F.col("m")).alias("s"))


def on_off(a: float, b: float) -> tuple[Column, Column]:
    """Diagonal and other entries of a I + (b / m) J."""
    return F.lit(a) + F.lit(b) / F.col("m"), F.lit(b) / F.col("m")


def clique_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(group_id, member): each clique as one group."""
    return cliques(spark, sf_dir).groupBy("col").agg(F.min("row").alias("group_id")).select("group_id", F.col("col").alias("member"))


# ---- chains: near-sighted in one dimension


def order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, chain, place, m): a customer's orders by date, then key."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    w = W.partitionBy("o_custkey")
    return o.select("o_orderkey", F.col("o_custkey").alias("chain"), F.row_number().over(w.orderBy("o_orderdate", "o_orderkey")).alias("place"), F.count(F.lit(1)).over(w).alias("m"))


def turn_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, chain, place, m): the turns of a conversation in order; id is conv_id * 2^20 + place."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    w = W.partitionBy("conv_id")
    c = c.select(F.col("conv_id").alias("chain"), F.row_number().over(w.orderBy("turn")).alias("place"), F.count(F.lit(1)).over(w).alias("m"))
    return c.select((F.col("chain") * (1 << 20) + F.col("place")).alias("id"), "chain", "place", "m")


def chain_matrix(chain: DataFrame, node: str, on: float, hop: float) -> DataFrame:
    """Tridiagonal blocks: ``on`` on the diagonal, ``hop`` between neighbours."""
    a = chain.select(F.col(node).alias("row"), "chain", "place")
    b = a.select(F.col("row").alias("col"), F.col("chain").alias("chain2"), F.col("place").alias("place2"))
    near = a.join(b, (F.col("chain") == F.col("chain2")) & (F.abs(F.col("place") - F.col("place2")) <= 1))
    return near.select("row", "col", F.when(F.col("row") == F.col("col"), F.lit(on)).otherwise(F.lit(hop)).alias("val"))


def chain_groups(chain: DataFrame, node: str) -> DataFrame:
    """(group_id, member): a whole chain in one group, which is exact."""
    return chain.select("chain", F.col(node).alias("member")).withColumn("group_id", F.min("member").over(W.partitionBy("chain"))).select("group_id", "member")


# ---- graphs


def copart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts bought together: val is the number of shared orders, on the diagonal the number of orders."""
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = li.select("l_orderkey", F.col("l_partkey").alias("col"))
    return li.join(other, "l_orderkey").groupBy(F.col("l_partkey").alias("row"), "col").agg(F.count(F.lit(1)).cast("double").alias("val"))


def copart_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(group_id, idx, own): the columns of ``copart`` as lists, by orders as a whole instead of by pairs of parts."""
    li = table(spark, sf_dir, "lineitem").where("l_orderkey is not null and l_partkey is not null")
    orders = li.groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("parts"))
    by = orders.select(F.explode("parts").alias("group_id"), "parts").groupBy("group_id")
    lists = by.agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("parts")))).alias("idx"))
    return lists.select("group_id", "idx", F.array("group_id").alias("own"))


#: Rows and columns of a tile in which pairs are counted (a place in it has 16 bits), rows and pairs looked at together.
MET, MET_ROWS, MET_PAIRS = 256, 1 << 18, 1 << 20


def met_in_sets(sets: DataFrame) -> DataFrame:
    """(row, col, val), row <> col: how many sets (key, member) hold both; a member counts once a set.

    Sets come whole to a task; their pairs go on as 16 bits each, in one row for each tile of places that a task finds
    pairs in, and are counted tile by tile.
    """
    rows = sets.where("key is not null and member is not null").select(F.col("key").cast("long").alias("set"), F.col("member").cast("long").alias("member"))

    def packed(x: np.ndarray, y: np.ndarray):
        ti, tj, place = x // MET, y // MET, (x % MET * MET + y % MET).astype(np.uint16)
        order = np.lexsort((tj, ti))
        ti, tj, place = ti[order], tj[order], place[order]
        first = np.flatnonzero(np.concatenate([[True], (ti[1:] != ti[:-1]) | (tj[1:] != tj[:-1])]))
        ends = (np.append(first, len(ti)) * 2).astype(np.int32)
        data = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(ends), pa.py_buffer(place)])
        return pa.RecordBatch.from_arrays([pa.array(ti[first]), pa.array(tj[first]), data], ["ti", "tj", "places"])

    def pairs_of(key: np.ndarray, member: np.ndarray):
        order = np.lexsort((member, key))
        key, member = key[order], member[order]
        new = np.concatenate([[True], (key[1:] != key[:-1]) | (member[1:] != member[:-1])])
        key, member = key[new], member[new]
        at, far, held, n = np.arange(len(key)), 1, [], 0
        while True:
            at = at[at + far < len(key)]
            at = at[key[at + far] == key[at]]
            if n and (not len(at) or n + len(at) > MET_PAIRS):
                yield packed(*(np.concatenate(x) for x in zip(*held, strict=True)))
                held, n = [], 0
            if not len(at):
                return
            held.append((member[at], member[at + far]))
            n, far = n + len(at), far + 1

    def pairs(batches):
        held, n = [], 0
        for b in batches:
            held.append((b.column("set").to_numpy(), b.column("member").to_numpy()))
            n += b.num_rows
            if n >= MET_ROWS:
                key, member = (np.concatenate(x) for x in zip(*held, strict=True))
                whole = int(np.searchsorted(key, key[-1]))  # the last set may go on
                if whole:
                    yield from pairs_of(key[:whole], member[:whole])
                held, n = [(key[whole:], member[whole:])], len(key) - whole
        if n:
            yield from pairs_of(*(np.concatenate(x) for x in zip(*held, strict=True)))

    def counted(t: pa.Table) -> pa.Table:
        met = np.bincount(np.frombuffer(b"".join(t.column("places").to_pylist()), np.uint16), minlength=MET * MET)
        place = np.flatnonzero(met)
        x, y, val = t.column("ti")[0].as_py() * MET + place // MET, t.column("tj")[0].as_py() * MET + place % MET, met[place].astype(float)
        return pa.table({"row": np.concatenate([x, y]), "col": np.concatenate([y, x]), "val": np.concatenate([val, val])})

    dealt = rows.repartition("set").sortWithinPartitions("set")
    tiles = dealt.mapInArrow(pairs, "ti long, tj long, places binary")
    return tiles.groupBy("ti", "tj").applyInArrow(counted, "row long, col long, val double")


def cosupplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers of one order: shared orders, the diagonal raised to one more than the row's sum, so S is dominant."""
    off = met_in_sets(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("key"), F.col("l_suppkey").alias("member")))
    ids = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("row"))
    return dominant(off, ids)


def dominant(off: DataFrame, ids: DataFrame) -> DataFrame:
    """Off-diagonal entries with a diagonal of 1 + the row's sum of absolute values."""
    total = off.groupBy(F.col("row").alias("_r")).agg(F.sum(F.abs("val")).alias("t"))
    diag = ids.join(total, F.col("row") == F.col("_r"), "left").select("row", F.col("row").alias("col"), (1 + F.coalesce("t", F.lit(0.0))).alias("val"))
    return off.select("row", "col", "val").unionByName(diag)


#: Vectors that one task compares with as many others.
TILE = 4096


def most_similar(spark: SparkSession, sf_dir: str, k: int = 8, tile: int = TILE) -> DataFrame:
    """(row, col, val): each embedding's ``k`` most similar others by cosine (9 decimals), ties to the smaller id.

    Vectors are dealt into blocks by a hash; each pair of blocks meets in one task as a matrix product, which keeps k
    of each row, and the blocks' best are merged by row. Work is all pairs; no task and no shuffle holds them.
    """
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    e = e.where(F.exists("v", lambda x: x != 0)).withColumn("dim", F.size("v"))
    blocks = max(1, -(-e.count() // tile))
    own = F.pmod(F.xxhash64("id"), F.lit(blocks))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<long>"))
    asked, given = e.select("id", "v", "dim", own.alias("a"), every.alias("b")), e.select("id", "v", "dim", every.alias("a"), own.alias("b"))

    def unit(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        ids = t.column("id").to_numpy()
        x = t.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        return ids, x / np.sqrt((x * x).sum(axis=1, keepdims=True))

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        row, col, val = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if left.num_rows and right.num_rows:
            (i, x), (j, y) = unit(left), unit(right)
            y, j = y[np.argsort(j)], np.sort(j)
            for at in range(0, len(i), 512):
                c = np.round(x[at : at + 512] @ y.T, 9)
                c[i[at : at + 512, None] == j] = -np.inf
                n = min(k, c.shape[1])
                best = np.argsort(-c, axis=1, kind="stable")[:, :n] if n else np.zeros((len(c), 0), np.int64)
                v = np.take_along_axis(c, best, axis=1)
                keep = np.isfinite(v)
                row.append(np.repeat(i[at : at + 512], n)[keep.ravel()])
                col.append(j[best][keep])
                val.append(v[keep])
        return pa.table({"row": np.concatenate(row), "col": np.concatenate(col), "val": np.concatenate(val)})

    found = asked.groupBy("dim", "a", "b").cogroup(given.groupBy("dim", "a", "b")).applyInArrow(meet, "row long, col long, val double")
    best = found.withColumn("_k", F.row_number().over(W.partitionBy("row").orderBy(F.desc("val"), "col"))).where(F.col("_k") <= k)
    return best.select("row", "col", "val")


def gram(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Overlap-like matrix of embeddings: each vector's ``k`` most similar by cosine, symmetrised, diagonally dominant."""
    best = most_similar(spark, sf_dir, k)
    both = best.union(best.select("col", "row", "val")).distinct()
    ids = table(spark, sf_dir, "embeddings").where(F.exists("embedding", lambda x: x != 0)).select(F.col("vec_id").alias("row"))
    return dominant(both, ids)


def sequences(spark: SparkSession, sf_dir: str, words: int = 5) -> DataFrame:
    """(doc_id, h): the distinct hashed word sequences of each document, whatever the number of documents that have them."""
    d = table(spark, sf_dir, "documents").select("doc_id", F.split(F.trim(F.regexp_replace("text", r"[ \t\n\x0B\f\r]+", " ")), " ").alias("w"))
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.size("w") - (words - 1), F.lit(1))))
    s = d.select("doc_id", at.alias("i"), "w").select("doc_id", F.md5(F.array_join(F.slice("w", F.col("i"), words), " ")).alias("h"))
    return s.where("doc_id is not null and h is not null").distinct()


#: Sequences that a task groups, about, and that a row of packed sequences is made of at most.
GROUPED, PACKED = 1_500_000, 2_000_000


def _mix(x: np.ndarray) -> np.ndarray:
    """64 bits well mixed, one to one."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _word_hashes(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit hashes of each word."""
    d = words.dictionary_encode()
    own, at = d.dictionary.to_numpy(zero_copy_only=False), d.indices.to_numpy()
    return tuple(hash_array(own, hash_key=key, categorize=False)[at] for key in ("nearfield-first0", "nearfield-second"))


def hashed_sequences(ids: np.ndarray, texts: pa.Array, words: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(h, check, number of the text) of the word sequences of each text, by h; h has 64 bits, check 8 more.

    A text with fewer words has one sequence, of all of them; an empty text has one of an empty word.
    """
    split = pc.split_pattern_regex(pc.utf8_trim(texts, " \t\n\x0b\f\r"), "[ \t\n\x0b\f\r]+")
    first, (a, b) = split.offsets.to_numpy().astype(np.int64), _word_hashes(split.flatten())
    first = first - first[0]
    many = np.diff(first)
    n = np.maximum(many - (words - 1), 1)
    doc = np.repeat(np.arange(len(ids)), n)
    at = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n) + first[doc]
    h, check = np.zeros(len(doc), np.uint64), np.zeros(len(doc), np.uint64)
    for k in range(words):
        there = at + k < first[doc + 1]
        spot = np.where(there, at + k, 0)
        h, check = np.where(there, _mix(h + a[spot] + np.uint64(1)), h), np.where(there, _mix(check + b[spot] + np.uint64(1)), check)
    check = (check >> np.uint64(56)).astype(np.uint8)
    order = np.argsort(h)
    h, check, doc = h[order], check[order], doc[order]
    new = np.ones(len(h), bool)  # a sequence that a text has again may stay where others' lie between
    new[1:] = (h[1:] != h[:-1]) | (check[1:] != check[:-1]) | (doc[1:] != doc[:-1])
    return h[new], check[new], doc[new]


def packed_planes(h: np.ndarray, check: np.ndarray, number: np.ndarray) -> bytes:
    """Sorted hashes and numbers of texts, their bytes by place: those in front hardly change, and compress to little."""
    return np.concatenate([h.astype(">u8").view(np.uint8).reshape(-1, 8).T, check[None, :], number.astype(">u4").view(np.uint8).reshape(-1, 4).T]).tobytes()


def shared_sets(spark: SparkSession, sf_dir: str, words: int = 5) -> DataFrame:
    """(docs, times): each different set of two or more documents that share word sequences, with how many they share.

    Sequences are known by a hash of 72 bits. A task packs those of its documents by ranges of hashes, sorted, their
    bytes by place, with numbers of documents in the pack, so that a sequence takes about 8 bytes of the one shuffle that
    all of them go through; only sets that two documents share leave it, each once.
    """
    d = table(spark, sf_dir, "documents").where("doc_id is not null and text is not null").select("doc_id", "text")
    size = d.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = int(max(3 * spark.sparkContext.defaultParallelism, size // 6 // GROUPED))

    def packs(ids: list, texts: list):
        ids = np.concatenate(ids)
        h, check, doc = hashed_sequences(ids, pa.concat_arrays(texts), words)
        ends = np.searchsorted(((h >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32), np.arange(parts + 1, dtype=np.uint64))
        used = [k for k in range(parts) if ends[k] < ends[k + 1]]
        rows = {"part": [], "n": [], "packed": [], "docs": []}
        for k in used:
            own = slice(ends[k], ends[k + 1])
            named, number = np.unique(doc[own], return_inverse=True)
            rows["part"].append(k)
            rows["n"].append(len(number))
            rows["packed"].append(packed_planes(h[own], check[own], number))
            rows["docs"].append(ids[named].tobytes())
        return pa.RecordBatch.from_arrays([pa.array(rows[c], t) for c, t in (("part", pa.int32()), ("n", pa.int64()), ("packed", pa.binary()), ("docs", pa.binary()))], ["part", "n", "packed", "docs"])

    def pack(batches):
        ids, texts, held = [], [], 0
        for b in batches:
            at = 0
            while at < b.num_rows:
                sizes = pc.binary_length(b.column(1).slice(at)).to_numpy(zero_copy_only=False).astype(np.int64)
                fit = max(1, int(np.searchsorted(np.cumsum(sizes), 6 * PACKED - held, "right")))
                part = b.slice(at, fit)
                ids.append(part.column(0).to_numpy())
                texts.append(part.column(1))
                held += int(sizes[: part.num_rows].sum())
                at += part.num_rows
                if held >= 6 * PACKED or at < b.num_rows:
                    yield packs(ids, texts)
                    ids, texts, held = [], [], 0
        if ids:
            yield packs(ids, texts)

    def sets(t: pa.Table) -> pa.Table:
        h, check, doc = [], [], []
        for n, packed, docs in zip(t.column("n").to_pylist(), t.column("packed").to_pylist(), t.column("docs").to_pylist(), strict=True):
            planes = np.frombuffer(packed, np.uint8).reshape(13, n)
            h.append(np.ascontiguousarray(planes[:8].T).view(">u8").ravel().astype(np.uint64))
            check.append(planes[8])
            doc.append(np.frombuffer(docs, np.int64)[np.ascontiguousarray(planes[9:].T).view(">u4").ravel()])
        h, check, doc = np.concatenate(h), np.concatenate(check), np.concatenate(doc)
        order = np.argsort(h)
        h = h[order]
        again = np.zeros(len(h), bool)
        again[1:] = h[1:] == h[:-1]
        again[:-1] |= again[1:]
        h, order = h[again], order[again]
        check, doc = check[order], doc[order]
        order = np.lexsort((doc, check, h))
        h, check, doc = h[order], check[order], doc[order]
        other = np.ones(len(h), bool)
        other[1:] = (h[1:] != h[:-1]) | (check[1:] != check[:-1])
        new = other.copy()
        new[1:] |= doc[1:] != doc[:-1]  # a document that is there twice counts once
        doc, first = doc[new], np.flatnonzero(other[new])
        length = np.diff(np.append(first, len(doc)))
        first, length = first[length > 1], length[length > 1]
        spots = np.repeat(first, length) + np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
        doc, start = doc[spots], np.cumsum(length) - length
        if not len(doc):
            return pa.table({"docs": pa.array([], pa.list_(pa.int64())), "times": pa.array([], pa.int64())})
        a, b = (np.add.reduceat(_mix(doc.astype(np.uint64) + np.uint64(k)), start) for k in (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03))
        order = np.lexsort((length, b, a))
        alike = np.ones(len(order), bool)
        alike[1:] = (np.diff(a[order]) != 0) | (np.diff(b[order]) != 0) | (np.diff(length[order]) != 0)
        at = np.flatnonzero(alike)
        one, times = order[at], np.diff(np.append(at, len(order)))
        spots = np.repeat(start[one], length[one]) + np.arange(length[one].sum()) - np.repeat(np.cumsum(length[one]) - length[one], length[one])
        docs = pa.ListArray.from_arrays(np.append(0, np.cumsum(length[one])).astype(np.int32), pa.array(doc[spots]))
        return pa.table({"docs": docs, "times": pa.array(times.astype(np.int64))})

    packed = d.mapInArrow(pack, "part int, n long, packed binary, docs binary").repartition(parts, "part")
    found = packed.groupBy("part").applyInArrow(sets, "docs array<long>, times long")
    return found.groupBy("docs").agg(F.sum("times").alias("times"))


def shared_sequences(s: DataFrame) -> DataFrame:
    """Rows (doc_id, h) whose sequence another document has too: the others make no entry of the near-duplicate graph."""
    return s.join(s.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"), "h", "left_semi")


def times_shared(s: DataFrame, v: DataFrame) -> DataFrame:
    """A v as rows (doc_id, v), A the near-duplicate graph: entries are the numbers of sequences that two documents share.

    ``s``: distinct (doc_id, h); ``v``: (doc_id, v), rows of one document are added. Each sequence sums v once, and each
    of its documents takes that sum without its own term, so no pairs are made and a sequence may have any number of
    documents. A document is in the result if it shares a sequence with another one that v names. With a column
    ``times`` a row of ``s`` stands for so many sequences of the same documents.
    """
    times = F.col("times") if "times" in s.columns else F.lit(1)
    v = v.where("v is not null").groupBy("doc_id").agg(F.sum("v").alias("v"))
    own = s.join(v, "doc_id", "left")
    sums = own.groupBy("h").agg(F.sum("v").alias("total"), F.count("v").alias("n")).where("n > 0")
    others = own.join(sums, "h").where(F.col("n") > F.col("v").isNotNull().cast("int"))
    return others.groupBy("doc_id").agg(F.sum((F.col("total") - F.coalesce("v", F.lit(0.0))) * times).alias("v"))


def page_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page to host edges: a matrix that is not symmetric."""
    p = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    first = p.groupBy("host").agg(F.min("page_id").alias("col"))
    return p.join(first, "host").select(F.col("page_id").alias("row"), "col", F.lit(1.0).alias("val"))


def grid_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Finite elements on a ring of all orders: stiffness (2, -1) as h and mass (4, 1) / 6 as s, neighbours by key."""
    n = table(spark, sf_dir, "orders").agg(F.count(F.lit(1))).first()[0]
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("col"))
    d = F.explode(F.array(F.lit(-1), F.lit(0), F.lit(1)))
    near = o.select("col", d.alias("d")).select(F.pmod(F.col("col") + F.col("d"), F.lit(n)).alias("row"), "col", "d")
    return near.select("row", "col", F.when(F.col("d") == 0, 2.0).otherwise(-1.0).alias("h"), F.when(F.col("d") == 0, 4.0 / 6).otherwise(1.0 / 6).alias("s"))


# ---- atoms


def water(spark: SparkSession, sf_dir: str, times: int = 1) -> tuple[DataFrame, Box]:
    """(atoms, box) of the homogeneous lattice, repeated along z."""
    part = table(spark, sf_dir, "part")
    box = box_of(part)
    return atoms(part, box, "water", times), box.repeated(times)


def mixed(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, Box]:
    """(atoms, box) of the lattice with several species and rare far-reaching sites."""
    part = table(spark, sf_dir, "part")
    box = box_of(part)
    return atoms(part, box, "mixed"), box


def atom_places(a: DataFrame, box: Box, model: ElementModel | None = None, reach: float | None = None) -> DataFrame:
    """(row, col) of atoms within the pair's cutoff (or one ``reach``), and each atom with itself."""
    own = a.select(F.col("atom_id").alias("row"), F.col("atom_id").alias("col"))
    if reach is not None:
        near = neighbours(a, box, reach).select(F.col("i").alias("row"), F.col("j").alias("col"))
        return near.unionByName(own).distinct()
    model = model or ElementModel()
    present = sorted(r.species for r in a.select("species").distinct().collect())  # a handful of species
    far = model.longest(present)
    kind = a.select("atom_id", "species")
    cutoff = F.lit(0.0)
    for p in present:
        for q in present:
            cutoff = F.when((F.col("si") == p) & (F.col("sj") == q), F.lit(model.cutoff(p, q))).otherwise(cutoff)
    near = neighbours(a, box, far).join(kind.withColumnsRenamed({"atom_id": "i", "species": "si"}), "i").join(kind.withColumnsRenamed({"atom_id": "j", "species": "sj"}), "j")
    near = near.where(F.col("r") < cutoff).select(F.col("i").alias("row"), F.col("j").alias("col"))
    return near.unionByName(own).distinct()


# ---- series


def noise_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, t, v): each user's readings in order, without their mean; t numbers them."""
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "value")
    w = W.partitionBy("user_id")
    return e.select(F.col("user_id").alias("id"), F.row_number().over(w.orderBy("ts", "event_id")).alias("t"), (F.col("value") - F.avg("value").over(w)).alias("v"))


def noise_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, step, mass, vx, vy, vz): three readings of a user in a row as one vector; incomplete ones are left out."""
    s = noise_series(spark, sf_dir).withColumn("step", F.floor((F.col("t") - 1) / 3)).withColumn("axis", (F.col("t") - 1) % 3)
    v = s.groupBy("id", "step").agg(F.count(F.lit(1)).alias("n"), *[F.max(F.when(F.col("axis") == k, F.col("v"))).alias(f"v{c}") for k, c in enumerate("xyz")])
    return v.where("n = 3").select("id", "step", F.lit(1.0).alias("mass"), "vx", "vy", "vz")
