"""Each operator against a plain version on small fixtures, with nulls, empty and long texts, ties and repeated rows."""

import hashlib
import os
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from nearfield.llm import block_search, components, fingerprints, hashing, jaccard_groups, language, line_dedup, mixing, pieces, shared, token_files, toxicity, warc
from nearfield.llm.elias_fano import EliasFano
from nearfield.llm.queries import CATEGORIES, tokenizer_path
from nearfield.llm.shared import shared_folder

SMALL, MIDDLE, LARGE = (f"/root/testdata/sf{x}" for x in ("0.001", "0.01", "0.1"))
WORD = re.compile(rb"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, keeper string, band int, n_lines string"


def odd_docs(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, and extra columns whose names clash."""
    long = " ".join(f"word{i % 7919}" for i in range(60_000))
    line = "A line that is shared by several documents"
    rows = [
        (1, f"{line}\nown one", "en", "b", 3, "k", 1, "x"),
        (2, f" {line.upper()}\t\nown two\n", "en", "b", 3, None, 1, None),
        (3, f"own three\n{line}", None, "a", None, "k", None, "x"),
        (3, f"own three\n{line}", None, "a", None, "k", None, "x"),
        (4, "", "de", None, 0, None, None, None),
        (5, None, None, None, None, None, None, None),
        (None, "no id at all but words enough here", "en", "é", 5, None, 2, "y"),
        (7, long, "en", "b", len(long), None, None, None),
        (8, long + " end", "en", "a", 1, None, None, None),
        (9, "  \n\t ", "en", "a", 5, None, None, None),
        (-4, "ein zwei", "de", "😀", 8, None, None, None),
        (10, "naïve 😀 text\nwith ▁ and\x00 zero", "fr", "", 9, None, None, None),
    ]
    return spark.createDataFrame(rows, DOCS)


def empty(spark, schema=DOCS):
    return spark.createDataFrame([], schema)


# ---- Elias-Fano and token files


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**40), max_size=700))
def test_elias_fano_returns_every_value(values):
    values.sort()
    e = EliasFano.of(values)
    data = b"xyz" + e.to_bytes()
    back, end = EliasFano.from_bytes(data, 3)
    assert end == len(data) and len(back) == len(values)
    assert back.all().tolist() == values
    assert [back.select(i) for i in range(len(values))] == values


def test_elias_fano_is_near_its_bound():
    values = np.cumsum(np.random.default_rng(1).integers(0, 900, 20_000))
    n, u = len(values), int(values[-1])
    assert len(EliasFano.of(values).to_bytes()) * 8 <= n * (2.4 + np.log2(u / n)) + 1000
    with pytest.raises(ValueError):
        EliasFano.of([3, 2])


def expected_tokens(rows):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    at, out = 0, []
    for d, text in rows:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        out.append((d, at, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids))))
        at += len(ids)
    return out


def test_token_files_hold_what_the_library_gives(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    rows = sorted(map(tuple, docs.collect()))
    got = sorted(map(tuple, token_files.token_table(docs.repartition(5), tokenizer_path("word_bpe_49k.json")).collect()))
    assert got == expected_tokens(rows)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=6), st.sampled_from(["H\u0331", "I\u0307s", "É,", "é.", "a.", "A..", "x,y", "<|endoftext|>", "a<|startoftext|>b", "<|ENDOFTEXT|>", "<|", "it's.", "'S'", "x" * 70, "ab" * 40 + "!", "it's.", "9.", "\x00", "\xa0", "Σας.", "．", "e\u0301."])), max_size=12))
def test_words_have_the_ids_that_they_have_in_a_text(words):
    text = " ".join(words).encode("utf-8", "ignore").decode()
    own = token_files.encoder(tokenizer_path("word_bpe_49k.json"))
    got = np.frombuffer(next(own.encode([text.encode()])), own.kind).tolist()
    assert [(0, 0, len(got) + 1, zlib.crc32(struct.pack(f"<{len(got) + 1}I", *got, 2)))] == expected_tokens([(0, text)])


@pytest.mark.parametrize(("step", "memo"), [(1, 0), (50, 2000), (1 << 20, 1 << 20)])
def test_long_texts_and_a_small_memo_give_the_same_ids(monkeypatch, step, memo):
    monkeypatch.setattr(token_files, "STEP", step)
    monkeypatch.setattr(token_files, "MEMO_BYTES", memo)
    own = token_files.WordEncoder(tokenizer_path("word_bpe_49k.json"))
    texts = ["", "one two, three's", "a <|endoftext|> b <|startoftext|>", "w" * 300 + " " + "Zoë! " * 40, "日本 end", " ".join(f"n{i}" for i in range(500)), " \n"]
    got = [np.frombuffer(x, own.kind).tolist() for x in own.encode([t.encode() for t in texts])]
    assert [(0, 0, len(g) + 1, zlib.crc32(struct.pack(f"<{len(g) + 1}I", *g, 2))) for g in got] == [expected_tokens([(0, t)])[0] for t in texts]
    assert 49407 in got[2] and own.held < memo + 200_000 and max(map(len, own.memo), default=0) <= token_files.LONG_WORD


def test_token_files_of_odd_documents(spark):
    docs = odd_docs(spark)
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    rows.sort(key=lambda r: (r[0] is not None, r[0] or 0))
    folder = shared_folder(spark, "t")
    path = tokenizer_path("word_bpe_49k.json")
    files = token_files.write_token_files(docs, path, folder, file_ids=1000)
    assert files.count() > 2
    got = token_files.read_token_files(spark, folder, files).orderBy("start").collect()
    assert [tuple(r) for r in got] == expected_tokens(rows)
    assert token_files.token_table(empty(spark), path).count() == 0


def test_a_document_is_reached_by_select():
    ids = [np.array(x, "<u2").tobytes() for x in ([1, 2, 3], [], [9], [4, 5])]
    f = token_files.TokenFile(token_files.pack([None, -5, 7, 7], ids, np.dtype("<u2")))
    assert [f.document(i).tolist() for i in range(4)] == [[1, 2, 3], [], [9], [4, 5]]
    assert f.doc_ids() == [None, -5, 7, 7]


# ---- mixing


def highest_quotients(votes, seats):
    import heapq
    from fractions import Fraction

    if not sum(votes):
        return [0] * len(votes)
    won = [0] * len(votes)
    heap = [(-Fraction(v), i) for i, v in enumerate(votes) if v]
    heapq.heapify(heap)
    for _ in range(seats):
        _, i = heapq.heappop(heap)
        won[i] += 1
        heapq.heappush(heap, (-Fraction(votes[i], 2 * won[i] + 1), i))
    return won


def test_apportionment_deals_by_highest_quotients(spark):
    draw = random.Random(4)
    rows, want = [], {}
    for g in range(60):
        votes = [draw.choice([0, 1, draw.randrange(10), draw.randrange(1000), draw.randrange(10**6)]) for _ in range(draw.randrange(1, 25))]
        seats = draw.randrange(0, 200)
        rows += [(g, i, float(v), seats) for i, v in enumerate(votes)]
        want |= {(g, i): q for i, q in enumerate(highest_quotients(votes, seats))}
    df = spark.createDataFrame(rows, "g int, i int, votes double, seats long")
    got = {(r.g, r.i): r.quota for r in mixing.apportion(df, ["g"], ["i"], "votes", "seats").collect()}
    assert got == want


def plain_targets(sizes, weights=(3, 1, 2), share=1.5, most=2):
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [None] * (None in sizes)
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    target, left, open_ = dict.fromkeys(names, 0.0), share * sum(sizes.values()), set(names)
    while open_ and left > 1e-9:
        whole = sum(w[s] for s in open_)
        give = {s: left * w[s] / whole for s in open_}
        left = 0.0
        for s in list(open_):
            target[s] += give[s]
            if target[s] > most * sizes[s]:
                left += target[s] - most * sizes[s]
                target[s] = most * sizes[s]
                open_.discard(s)
    return target


@pytest.mark.parametrize("which", ["odd", MIDDLE])
def test_mix_comes_near_its_targets(spark, which):
    docs = odd_docs(spark) if which == "odd" else spark.read.parquet(f"{which}/documents.parquet")
    rows = mixing.mix(docs, shard_words=4096).collect()
    sizes = defaultdict(int)
    for r in docs.collect():
        sizes[r.source] += len(WORD.findall((r.text or "").encode()))
    target = plain_targets(sizes)
    taken = Counter()
    for r in rows:
        assert 0 <= r.taken <= 2 * r.size and r.source_size == sizes[r.source]
        assert r.target == pytest.approx(target[r.source], abs=1e-6)
        taken[r.source] += r.taken
    assert len(rows) == docs.count()
    for s, t in target.items():
        shards = -(-sizes[s] // 4096)
        assert abs(taken[s] - t) <= 32 * (shards + 1)
    again = mixing.mix(docs.repartition(3), shard_words=4096).collect()
    assert Counter(map(tuple, rows)) == Counter(map(tuple, again))


def test_mix_of_nothing(spark):
    assert mixing.mix(empty(spark)).count() == 0
    none = spark.createDataFrame([(1, None, None), (2, " ", "a")], "doc_id long, text string, source string")
    assert sorted((r.doc_id, r.size, r.target, r.taken) for r in mixing.mix(none).collect()) == [(1, 0, 0.0, 0), (2, 0, 0.0, 0)]


# ---- nearest neighbours


def plain_nearest(rows, k=10):
    ok = {i: np.array(v, float) for i, v in rows if v is not None and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    out = []
    for q in ok:
        if q % 100 == 0:
            best = sorted((float(np.sqrt(sum((a - b) ** 2 for a, b in zip(ok[q], ok[c], strict=True)))), c) for c in ok if c != q and len(ok[c]) == len(ok[q]))
            out += [(q, n + 1, c, s) for n, (s, c) in enumerate(best[:k])]
    return sorted(out)


@pytest.mark.parametrize("block", [7, 5000])
def test_nearest_is_exact(spark, block):
    draw = np.random.default_rng(2)
    rows = [(int(i), draw.normal(size=6).astype(np.float32).tolist()) for i in range(0, 900, 3)]
    rows += [(1000 + i, rows[0][1]) for i in range(30)]  # ties
    rows += [(2000, None), (2100, [0.0] * 6), (2200, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (2300, [float("nan")] * 6), (2400, [1.0, 2.0]), (2401, [1.5, 2.0]), (2500, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").selectExpr("*", "1 as part", "'x' as score")
    got = block_search.nearest(df, df.vec_id % 100 == 0, block=block).collect()
    rows = [(i, v and [None if x is None else float(np.float32(x)) for x in v]) for i, v in rows]
    assert sorted((r.query_id, r.rank, r.vec_id, round(r.score, 9)) for r in got) == [(a, b, c, round(d, 9)) for a, b, c, d in plain_nearest(rows)]
    assert block_search.nearest(df.limit(0), df.vec_id % 100 == 0).count() == 0
    twice = df.union(df)
    assert block_search.nearest(twice, twice.vec_id % 100 == 0, block=block).count() == len(got)


@pytest.mark.parametrize("size", [1e200, 1e-200, 3e307])
def test_nearest_of_very_large_and_small_components(spark, size):
    draw = np.random.default_rng(4)
    x = draw.normal(size=(60, 5)) / 4
    rows = [(i * 10, (x[i] * size).tolist()) for i in range(50)] + [(i * 10, x[i].tolist()) for i in range(50, 60)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in block_search.nearest(df, df.vec_id % 100 == 0, block=17).collect()}
    exact = {i: np.array(v, np.longdouble) for i, v in rows}
    for q in (i for i in exact if i % 100 == 0):
        best = sorted((float(np.sqrt(((exact[q] - exact[c]) ** 2).sum())), c) for c in exact if c != q)[:10]
        assert [got[q, n + 1][1] for n in range(10)] == pytest.approx([d for d, _ in best], rel=1e-12)
        assert {got[q, n + 1][0] for n in range(10)} == {c for _, c in best} or q >= 500


def test_quantisation_bounds_hold():
    draw = np.random.default_rng(3)
    x, y = draw.normal(size=(50, 64)), draw.normal(size=(80, 64)) * 100
    (a, s, n, e), (b, t, m, f) = block_search.quantise(x), block_search.quantise(y)
    approx = (s[:, None] * t) * (a.astype(float) @ b.T.astype(float))
    assert (np.abs(x @ y.T - approx) <= n[:, None] * f + e[:, None] * (m + f) + 1e-9).all()


# ---- line dedup


def plain_dedup(rows, least=20, documents=3):
    key = lambda s: s.strip(" \t\n\x0b\x0c\r").translate({c: c + 32 for c in range(65, 91)})
    held = defaultdict(set)
    for d, text in rows:
        for k in {key(x) for x in (text or "").split("\n")}:
            held[k].add(d if d is not None else -(2**63))
    out = []
    for d, text in rows:
        own = d if d is not None else -(2**63)
        lines = (text or "").split("\n")
        kept = [x for x in lines if len(key(x)) < least or len(held[key(x)]) < documents or max(held[key(x)]) == own]
        out.append((d, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return Counter(out)


@pytest.mark.parametrize("which", ["odd", SMALL])
def test_line_dedup_against_a_plain_version(spark, which):
    docs = odd_docs(spark) if which == "odd" else spark.read.parquet(f"{which}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    out = line_dedup.dedup_lines(docs)
    assert [c for c in docs.columns if c != "n_lines"] == [c for c in out.columns if c not in ("n_lines", "n_dropped")]
    got = Counter((r.doc_id, r.n_lines, r.n_dropped, hashlib.sha256((r.text or "").encode()).hexdigest()) for r in out.collect())
    assert got == plain_dedup(rows)
    assert line_dedup.dedup_lines(empty(spark)).count() == 0


def test_rows_that_share_a_doc_id_are_one_document_as_in_the_sql(spark):
    import duckdb

    from nearfield.llm.queries import ORACLES

    line, other = "a line that is long enough to count", "another line that is long enough"
    rows = [(1, f"{line}\n{other}"), (2, line), (2, line + " "), (3, other), (4, f"x\n{other.upper()}")]
    got = line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r.doc_id, r.n_dropped) for r in got) == [(1, 1), (2, 0), (2, 0), (3, 1), (4, 0)]
    with duckdb.connect() as db:
        db.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
        db.executemany("INSERT INTO documents VALUES (?, ?)", rows)
        want = db.execute(f"SELECT doc_id, n_dropped FROM ({ORACLES['op5_line_dedup']}) ORDER BY 1").fetchall()
    assert want == [(1, 1), (2, 0), (3, 1), (4, 0)]


# ---- pieces


def varint(n):
    out = b""
    while True:
        n, b = n >> 7, n & 127
        out += bytes([b | 128 * bool(n)])
        if not n:
            return out


def message(data):
    """(field, wire type, value) of a serialised message."""

    def number(i):
        n = s = 0
        while True:
            n |= (data[i] & 127) << s
            s, i = s + 7, i + 1
            if data[i - 1] < 128:
                return n, i

    i = 0
    while i < len(data):
        tag, i = number(i)
        if tag & 7 == 2:
            n, i = number(i)
            yield tag >> 3, 2, data[i : i + n]
            i += n
        elif tag & 7 == 5:
            yield tag >> 3, 5, data[i : i + 4]
            i += 4
        else:
            n, i = number(i)
            yield tag >> 3, 0, n


def field(f, w, v):
    return varint(f << 3 | w) + (varint(len(v)) + v if w == 2 else varint(v) if w == 0 else v)


@pytest.fixture(scope="module")
def library():
    """The same pieces and scores as a unigram model of the library."""
    from sentencepiece import SentencePieceProcessor

    path = tokenizer_path("piece_bpe_32k.model")
    m = pieces.model(path)
    out, k = b"", 0
    for f, w, v in message(open(path, "rb").read()):
        if f == 1:
            if m.text[k] and not m.is_byte[k]:
                v = b"".join(field(a, b, c) if a != 2 else field(2, 5, struct.pack("<f", m.score[k])) for a, b, c in message(v))
            k += 1
        if f == 2:
            v = b"".join(field(3, 0, 1) if a == 3 else field(a, b, c) for a, b, c in message(v))
        out += field(f, w, v)
    return m, SentencePieceProcessor(model_proto=out)


ODD_TEXTS = ["", " ", "a", "  two  blanks ", "héllo 😀 wörld\n\n x", "日本語 テキスト", "a\tb\x00c", "x" * 3000, "<s></s><unk><0x41>", "ab" * 40 + " " + "é" * 70]


def test_viterbi_finds_the_library_s_best_path(spark, library):
    m, sp = library
    texts = [r.text for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()] + ODD_TEXTS
    same = 0
    for t in texts:
        ours, theirs = m.encode(t), sp.encode(t)
        same += ours == theirs
        if ours != theirs:  # equal scores: the library's sums are in single precision
            assert sum(m.score[ours]) == pytest.approx(sum(m.score[theirs]), rel=1e-5)
        assert m.decode(ours).decode() == t
        assert sp.decode(ours) == t or not t
    assert same > 0.9 * len(texts)


def test_both_viterbi_forms_agree(library):
    m, _ = library
    draw = random.Random(6)
    some = ["".join(draw.choice("abcdeéß日😀 .\n") for _ in range(draw.randrange(1, 40))).encode() for _ in range(500)]
    assert m._many(some) == [m._one(s) for s in some]


def test_pieces_of_odd_documents(spark, library):
    m, _ = library
    path = tokenizer_path("piece_bpe_32k.model")
    docs = odd_docs(spark)
    out = pieces.encode_pieces(docs, path)
    got = Counter((r.doc_id, r.n_ids, r.ids_crc32, r.round_trip) for r in out.collect())
    want = Counter()
    for r in docs.collect():
        ids = m.encode(r.text or "")
        want[(r.doc_id, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids)), "▁" not in (r.text or ""))] += 1
    assert got == want
    back = Counter((r.doc_id, r.text) for r in pieces.decode_pieces(out, path).collect())
    assert back == Counter((r.doc_id, (r.text or "").replace("▁", " ")) for r in docs.collect())
    assert pieces.encode_pieces(empty(spark), path).count() == 0


# ---- fingerprints


def shingles(text, k):
    w = [x.decode() for x in WORD.findall((text or "").encode().lower())]
    return {" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def jaccard(a, b):
    return len(a & b) / len(a | b) if a | b else 0.0


@pytest.mark.parametrize("rows_a_range", [2, 50, 4096])
def test_edited_texts_meet_the_next_document(spark, monkeypatch, rows_a_range):
    monkeypatch.setattr(fingerprints, "RANGE_ROWS", rows_a_range)
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = sorted(((r.doc_id, r.text) for r in docs.collect()), reverse=True)
    got = {r.doc_id: r for r in fingerprints.edited_fingerprints(docs.repartition(4)).collect()}
    assert len(got) == len(rows)
    error = []
    for (d, text), (_, after) in zip(rows, rows[1:] + rows[:1], strict=True):
        cut = len(text) - len(text) // 3
        edited = text[:cut] + after[: len(text) // 3]
        r = got[d]
        assert (r.n_chars, r.edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        error.append(r.near_edited - jaccard(shingles(text, 5), shingles(edited, 5)))
        error.append(r.near_next - jaccard(shingles(text, 5), shingles(after, 5)))
    assert abs(np.mean(error)) < 0.01 and np.std(error) < 0.05


def test_fingerprints_of_odd_documents(spark):
    got = fingerprints.edited_fingerprints(odd_docs(spark)).collect()
    assert len(got) == odd_docs(spark).count()
    by = defaultdict(set)
    for r in fingerprints.add_fingerprints(odd_docs(spark)).collect():
        by[r.doc_id].add(r.fingerprint)
    assert len(by[3]) == 1 and by[4] == by[5] == by[9]
    assert fingerprints.edited_fingerprints(empty(spark)).count() == 0
    one = fingerprints.edited_fingerprints(odd_docs(spark).where("doc_id = 1")).collect()
    assert len(one) == 1 and one[0].near_next == 1.0


def test_bands_find_near_pairs(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    sets = {r.doc_id: shingles(r.text, 5) for r in docs.collect()}
    classes = {r.doc_id: r.class_id for r in fingerprints.near_classes(docs, 5, 5, 52).collect()}
    assert classes == {d: min(e for e in sets if sets[e] == s) for d, s in sets.items()}
    for r in fingerprints.near_pairs(docs).collect():
        assert r.jaccard == pytest.approx(jaccard(sets[r.a], sets[r.b])) and r.jaccard >= 0.8


@pytest.mark.parametrize("block", [6000, 9])
def test_bands_find_all_near_pairs(spark, block):
    rows = list(enumerate(families(block)))
    sets = {d: shingles(t, 5) for d, t in rows}
    first = {d: min(e for e in sets if sets[e] == s) for d, s in sets.items()}
    reps = [d for d in sets if first[d] == d]
    want = {(a, b): jaccard(sets[a], sets[b]) for a in reps for b in reps if a < b and jaccard(sets[a], sets[b]) >= 0.8}
    got = fingerprints.near_pairs(spark.createDataFrame(rows, "doc_id long, text string"), block=block).collect()
    assert len(got) == len(want) and {(r.a, r.b): r.jaccard for r in got} == pytest.approx(want)
    assert len(want) > len({b for _, b in want})  # more than one partner each


# ---- Jaccard join and components


def plain_components(sets, percent):
    ids = sorted(sets)
    root = {d: d for d in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            m = len(sets[a] & sets[b])
            if m and 100 * m >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: find(d) for d in ids}


def families(seed, n=40):
    """Families of near copies at similarities around the threshold, copies, and unrelated texts."""
    draw = random.Random(seed)
    new = lambda: f"w{draw.randrange(5000)}"
    out = []
    for _ in range(n):
        base = [new() for _ in range(draw.choice([2, 5, 12, 40, 150]))]
        for _ in range(draw.choice([1, 1, 2, 12])):
            own = list(base)
            for _ in range(draw.randrange(0, 1 + len(own) // 30)):
                own[draw.randrange(len(own))] = new()
            out.append(" ".join(own).upper() if draw.random() < 0.3 else "\n".join(own))
    return out


@pytest.mark.parametrize(("words", "percent", "block"), [(3, 90, 6000), (3, 90, 9), (5, 80, 6000), (5, 80, 9)])
def test_jaccard_components_are_exact(spark, words, percent, block):
    texts = families(words + block)
    rows = list(enumerate(texts)) + [(9000, None), (9001, ""), (9002, " \n"), (9003, "one"), (9004, "ONE")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' as band", "1 as component", "2 as node")
    got = jaccard_groups.jaccard_components(df, words, percent, block).collect()
    sets = {d: shingles(t, words) for d, t in rows}
    assert {r.doc_id: r.n_shingles for r in got} == {d: len(s) for d, s in sets.items()}
    assert {r.doc_id: r.component_id for r in got} == plain_components(sets, percent)


@pytest.mark.parametrize("block", [6000, 9])
def test_the_jaccard_join_counts_every_link(spark, block):
    texts = families(3 + block)
    rows = list(enumerate(texts + texts[:9])) + [(9000, None), (9001, ""), (9003, "one"), (9004, "ONE")]
    sets = {d: shingles(t, 3) for d, t in rows}
    want = {d: sum(e != d and 100 * len(s & t) >= 90 * len(s | t) > 0 for e, t in sets.items()) for d, s in sets.items()}
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = jaccard_groups.jaccard_components(df, 3, 90, block).collect()
    assert {r.doc_id: r.n_links for r in got} == want and max(want.values()) > 2
    bare = jaccard_groups.jaccard_components(df, 3, 90, block, links=False).collect()
    assert {tuple(r) for r in bare} == {(r.doc_id, r.n_shingles, r.component_id) for r in got}


def test_jaccard_of_odd_documents(spark):
    got = {r.doc_id: r for r in jaccard_groups.jaccard_components(odd_docs(spark), 3, 90).collect()}
    assert set(got) == {None, -4, 1, 2, 3, 4, 5, 7, 8, 9, 10} and got[None].component_id is None and got[None].n_shingles == 6
    assert got[8].component_id == 7 and got[5].component_id == 5 and got[5].n_shingles == 0
    assert jaccard_groups.jaccard_components(empty(spark), 3, 90).count() == 0
    left = jaccard_groups.drop_near_copies(odd_docs(spark)).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in left) == [(False, d) for d in (-4, 1, 2, 3, 3, 4, 5, 7, 9, 10)] + [(True, 0)]


def test_the_matrix_opens_every_group_that_it_must():
    draw = np.random.default_rng(8)
    base = draw.integers(0, 2**63, 400).astype(np.uint64)
    sets = [np.unique(np.concatenate([base[draw.random(400) < 0.97], draw.integers(0, 2**63, 8).astype(np.uint64)])) for _ in range(150)]
    for percent in (80, 90, 93):
        m = jaccard_groups.TokenGroupMatrix(sets, percent, group=7)
        for i in range(0, 150, 10):
            want = [j for j in range(150) if j != i and 100 * (c := np.intersect1d(sets[i], sets[j]).size) >= percent * (sets[i].size + sets[j].size - c)]
            assert sorted(m.reach(i)) == want


@settings(max_examples=8, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 25), st.integers(0, 25)), max_size=40))
def test_components_are_those_of_union_find(spark, edges):
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    root = {x: x for e in edges for x in e if e[0] != e[1]}
    for _ in root:
        for a, b in edges:
            if a != b:
                root[a] = root[b] = min(root[a], root[b])
    assert got == root


def test_components_of_a_long_path(spark):
    edges = spark.range(300).selectExpr("id as a", "id + 1 as b").union(spark.createDataFrame([(None, 5), (7, 7)], "a long, b long"))
    got = components.connected_components(edges).collect()
    assert len(got) == 301 and {r.component for r in got} == {0}


@pytest.mark.parametrize("salted", [True, False])
def test_components_of_a_star_and_its_rim(spark, monkeypatch, salted):
    monkeypatch.setattr(components, "PARTS", 5 if salted else 1)
    monkeypatch.setattr(components, "PART_EDGES", 50)
    edges = spark.range(1, 400).selectExpr("id as a", "1000 as b").union(spark.range(500, 560).selectExpr("500 as a", "id as b"))
    got = components.connected_components(edges.union(spark.createDataFrame([(399, 530)], "a long, b long"))).collect()
    assert len(got) == 399 + 1 + 60 and {r.component for r in got} == {1}


def test_a_part_is_dealt_in_bounded_blocks(spark, monkeypatch):
    monkeypatch.setattr(jaccard_groups, "MOST_SHINGLES", 500)
    sets = spark.range(60).selectExpr("id as doc_id", "100L as n_shingles", "array(7L) as bands").union(spark.range(90, 92).selectExpr("id", "1L", "array(8L)"))
    tasks = defaultdict(list)
    for r in jaccard_groups.deal(sets, 30).collect():
        tasks[r.part, r.x, r.y].append((r.node, r.side))
    blocks = max(y for p, _, y in tasks if p == 0) + 1
    assert blocks >= 12 and set(tasks) >= {(0, a, b) for a in range(blocks) for b in range(a, blocks) if (0, a, b) in tasks}
    home = {n: x for (p, x, y), own in tasks.items() if x == y for n, _ in own}
    for a in range(60):
        for b in range(a):
            x, y = sorted((home[a], home[b]))
            assert {a, b} <= {n for n, _ in tasks[0, x, y]}
    assert sorted(tasks[90, 0, 0]) == [(90, 0), (91, 0)]


@pytest.mark.parametrize("percent", [80, 90])
def test_pairs_at_the_threshold_share_a_band(percent):
    draw = np.random.default_rng(percent)
    rows, bands = jaccard_groups.bands_for(percent)
    own, missed = fingerprints.hasher(rows * bands), 0
    for _ in range(3000):
        pool = draw.integers(0, 2**63, 100).astype(np.uint64)
        k = (100 - percent) // 2
        a, b = np.unique(pool[: 100 - k]), np.unique(np.concatenate([pool[: 100 - 2 * k], pool[100 - k :]]))
        assert 100 * np.intersect1d(a, b).size >= percent * np.union1d(a, b).size
        missed += not np.intersect1d(hashing.band_keys(own.signature(a), rows), hashing.band_keys(own.signature(b), rows)).size
    assert missed == 0


@pytest.mark.parametrize(("piece", "back"), [(7, 7), (16, 8), (1 << 20, 1 << 16)])
def test_word_hashes_do_not_depend_on_pieces(monkeypatch, piece, back):
    draw = random.Random(piece)
    texts = [bytes(draw.choice(b"abc  \n\xc3z") for _ in range(n)) for n in (0, 1, 6, 7, 8, 40, 300)] + [b"x" * 99, b" " * 50, b"ab " + b"y" * 90 + b" c"]
    want = [hashing.word_hashes(t, (4, 5, 6)).tolist() for t in texts]
    monkeypatch.setattr(hashing, "PIECE", piece)
    monkeypatch.setattr(hashing, "BACK", back)
    assert [hashing.word_hashes(t, (4, 5, 6)).tolist() for t in texts] == want


def test_word_hashes_tell_words_apart():
    data = "Some words, some MORE words\x0b\x0cand\x1cone  é 日本 ".encode().lower()
    words = data.split()
    h = hashing.word_hashes(data)
    assert len(h) == len(words)
    assert len({(w, x) for w, x in zip(words, h.tolist(), strict=True)}) == len(set(words)) == len(set(h.tolist()))


# ---- language


def test_language_of_held_out_documents(spark):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    out = {r.doc_id: r.lang_pred for r in language.identify(docs, language.learn(docs, docs.doc_id % 4 != 0)).collect()}
    held = [(r.lang, out[r.doc_id]) for r in docs.where("doc_id % 4 = 0").collect()]
    assert sum(a == b for a, b in held) >= 0.98 * len(held)


def test_language_of_odd_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    model = language.learn(docs, docs.doc_id >= 0)
    got = language.identify(odd_docs(spark), model).collect()
    assert len(got) == odd_docs(spark).count()
    assert {r.doc_id: (r.lang_pred, r.score) for r in got if r.doc_id in (4, 5, 9)} == {d: ("und", 0.0) for d in (4, 5, 9)}
    assert all(0 <= r.score <= 1 for r in got)
    far = spark.createDataFrame([(1, "これは日本語の文章です"), (2, "0 1 2 !")], "doc_id long, text string")
    assert [r.rejected for r in language.identify(far, model).orderBy("doc_id").collect()] == [True, True]
    none = language.learn(empty(spark), F.col("doc_id").isNotNull())
    assert {r.lang_pred for r in language.identify(odd_docs(spark), none).collect()} == {"und"}


def plain_ngrams(text):
    """Counts of hashed n-grams, one character at a time."""
    if text is None or not any(ch.isalpha() for ch in text.lower()):
        return None
    c, full = " ", 2**32 - 1
    for ch in text.lower():
        if ch.isalpha():
            c += ch
        elif len(c) > 1 and c[-1] != " ":
            c += " "
    c += " "
    out = Counter()
    for i in range(len(c)):
        for n in (1, 2, 3):
            if i + n > len(c):
                continue
            o = [ord(x) * 0x9E3779B1 & full for x in c[i : i + n]]
            h = o[0]
            if n > 1:
                h = ((o[0] ^ o[0] >> 15) * 0x85EBCA77 + o[1]) & full
            if n == 3:
                h = ((h ^ h >> 13) * 0xC2B2AE3D + o[2]) & full
            h = h * {1: 1, 2: 0x27D4EB2F, 3: 0x165667B1}[n] & full
            out[(h ^ h >> 16) * 0x9E3779B1 & full] += 1
    counts = Counter()
    for h, m in out.items():
        counts[h >> 19] += m
    return counts


@pytest.mark.parametrize("piece", [1, 2, 3, 7, 1 << 19])
def test_ngrams_are_those_of_a_plain_count(monkeypatch, piece):
    monkeypatch.setattr(language, "PIECE", piece)
    for text in ("", None, "7 !", "a", "Ab", " ab  C-d\n\n", "Où est l'Été ?", "x1y", "ΑΣ 日本 σ", "a" * 50 + "!!"):
        got, want = language.ngram_counts(text), plain_ngrams(text)
        assert (got is None) == (want is None)
        if want:
            assert {i: int(got[i]) for i in np.flatnonzero(got)} == dict(want)


def plain_language(rows, texts, k=4, seed=5):
    """Dense TF-IDF vectors, k-means and the nearest centroid, as a plain program has them."""
    counts = [(lang, np.array([c.get(i, 0) for i in range(language.FEATURES)], float)) for lang, text in rows if (c := plain_ngrams(text))]
    seen = sum((n > 0).astype(int) for _, n in counts)
    idf = np.log((1 + len(counts)) / (1 + seen)) + 1

    def unit(x):
        return x / max(np.sqrt((x * x).sum()), 1e-12)

    draw = np.random.default_rng(seed)
    centres = []
    for lang in sorted({n for n, _ in counts}):
        x = [unit(np.log1p(n) * idf) for own, n in counts if own == lang]
        c = [x[i] for i in draw.choice(len(x), min(k, len(x)), replace=False)]
        for _ in range(12):
            own = [max(range(len(c)), key=lambda j: v @ c[j]) for v in x]
            c = [unit(sum(v for v, o in zip(x, own, strict=True) if o == j)) if j in own else c[j] for j in range(len(c))]
        own = [max(range(len(c)), key=lambda j: v @ c[j]) for v in x]
        centres += [(lang, c[j]) for j in range(len(c)) if j in own]
    out = []
    for text in texts:
        c = plain_ngrams(text)
        if not c:
            out.append(("und", 0.0))
            continue
        v = unit(np.log1p(np.array([c.get(i, 0) for i in range(language.FEATURES)])) * idf)
        lang, centre = max(centres, key=lambda x: v @ x[1])
        out.append((lang, min(1.0, max(0.0, float(v @ centre)))))
    return out


def test_the_language_query_is_a_plain_nearest_centroid(spark):
    from nearfield.llm.queries import op8_language_centroids

    got = {r.doc_id: r for r in op8_language_centroids(spark, SMALL).collect()}
    rows = spark.read.parquet(f"{SMALL}/documents.parquet").selectExpr("doc_id", "text", "lang", "xxhash64(doc_id, 11) AS o").collect()
    held = {r.doc_id: zlib.crc32(str(r.doc_id).encode()) % 5 == 0 for r in rows}
    assert {d: r.held_out for d, r in got.items()} == held
    # few rows: all are drawn; the order of the draw is that of the hash
    fit = [(r.lang, r.text) for r in sorted(rows, key=lambda r: r.o) if not held[r.doc_id] and r.lang is not None and r.text is not None]
    want = plain_language(fit, [r.text for r in rows])
    same = [got[r.doc_id].lang_pred == lang for r, (lang, _) in zip(rows, want, strict=True)]
    near = [abs(got[r.doc_id].score - score) < 1e-4 for r, (_, score) in zip(rows, want, strict=True)]
    assert np.mean(same) >= 0.99 and np.mean(near) >= 0.97  # single precision may settle a close call otherwise


def test_counts_of_very_common_ngrams_do_not_wrap():
    at, n = np.array([3, 9]), np.array([65_536, 1], np.uint32)
    m = language.fit([("x", at, n), ("y", np.array([9]), np.array([1]))], centroids=1)
    assert m.langs == ["x", "y"] and m.centroids[0][3] > 0.9


# ---- WARC


def test_warc_round_trip_of_odd_pages(spark):
    big = "<p>" + "é" * 700 + "</p>"
    rows = [(1, "http://a.example/x", big), (2, None, big), (3, "http://b.example", big), (4, "http://c.example/\r\nX: y", "small"), (5, "u", "small"), (6, "", None), (None, "n", big), (7, "v", ""), (8, "w", "z" * 200_000), (8, "w", "z" * 200_000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'d' as digest", "1 as file")
    got = Counter(map(tuple, warc.digest_rows(warc.captures(pages)).collect()))
    want = Counter()
    for p, _, html in rows:
        body = (html or "").encode()
        to = 3 if html == big and p != 3 else None
        want[(p, len(body), hashlib.sha1(body).hexdigest(), "revisit" if to else "response", to)] += 1
    assert got == want
    assert warc.captures(pages.limit(0)).count() == 0


def test_files_of_a_lost_attempt_are_no_part_of_the_archive(spark):
    folder = shared_folder(spark, "w")
    pages = spark.createDataFrame([(1, "http://a", "x"), (2, "http://b", "y")], "page_id long, url string, html string")
    files = warc.write_archives(pages, folder)
    token_files.put(folder, "part-000000-000007-0123456789ab.warc.gz", warc.capture_records(1, "http://a", b"x", None, "0-0"))
    got = warc.digest_rows(warc.assemble(warc.read_records(spark, folder, files))).collect()
    assert sorted(r.page_id for r in got) == [1, 2]
    assert warc.read_records(spark, folder).count() == 9


def test_passing_files_are_removed(spark, monkeypatch):
    made = []
    for module in (warc, token_files):
        monkeypatch.setattr(module, "shared_folder", lambda s, label: made.append(shared_folder(s, label)) or made[-1])
    docs = spark.createDataFrame([(1, "http://a", "x")], "page_id long, url string, html string")
    assert warc.captures(docs).count() == 1
    assert token_files.token_table(docs.selectExpr("page_id as doc_id", "html as text"), tokenizer_path("word_bpe_49k.json")).count() == 1
    assert len(made) == 2 and not any(os.path.exists(f.removeprefix("file:").replace("///", "/")) for f in made)


def test_a_cluster_needs_a_shared_folder():
    class Session:
        class conf:
            get = staticmethod(lambda k, d=None: d)

        class sparkContext:
            master = "spark://host:7077"
            getCheckpointDir = staticmethod(lambda: None)

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        shared.shared_root(Session)


def test_transactions_without_all_records(spark):
    folder = shared_folder(spark, "w")
    capture = warc.capture_records(5, "http://a/b", b"body", None, "0-0")
    alone = warc.record("request", "urn:x", {"WARC-Concurrent-To": "<urn:lost>"}, b"GET", "application/http;msgtype=request")
    token_files.put(folder, "a.warc.gz", capture)
    token_files.put(folder, "b.warc.gz", alone)
    got = {r.capture_id: r for r in warc.assemble(warc.read_records(spark, folder)).collect()}
    assert got["urn:lost"].response is None and got["urn:lost"].request.record_id == "urn:x"
    whole = got["urn:capture:5:0-0"]
    assert whole.response.payload_bytes == 4 and whole.request is not None and whole.metadata.fields["page-id"] == "5"
    with pytest.raises(ValueError):
        list(warc.members(capture[:-5]))


# ---- toxicity


def test_toxic_documents_are_found(spark):
    docs, labels = (spark.read.parquet(f"{LARGE}/{t}.parquet") for t in ("documents", "labels"))
    chain = toxicity.learn(docs, labels.where("doc_id % 3 <> 0"), CATEGORIES)
    got = {r.doc_id: r for r in toxicity.predict(docs, chain).collect()}
    held = [(r.toxic, got[r.doc_id].is_toxic) for r in labels.where("doc_id % 3 = 0 and toxic is not null").collect()]
    assert sum(b for a, b in held if not a) <= 0.01 * len(held)
    assert sum(b for a, b in held if a) >= 0.9 * sum(a for a, _ in held)


def plain_features(text):
    """Numbers of a text's words and of longer words' beginnings, by arithmetic on Python's integers."""
    full, base, out = 2**64 - 1, 0xD6E8FEB86659FD93, set()

    def spread(x):
        x = (x ^ x >> 32) * 0xD6E8FEB86659FD93 & full
        x = (x ^ x >> 32) * 0xC2B2AE3D27D4EB4F & full
        return x ^ x >> 29

    for word in re.findall(rb"(?:[^\x00-\x7f]|[0-9A-Za-z])+", (text or "").encode()):
        word = word.lower()
        value = lambda w: sum((c + 1) * pow(base, i, 2**64) for i, c in enumerate(w)) & full
        out.add(spread((value(word) + len(word)) & full) >> 46)
        out |= {spread((value(word[:k]) - k) & full) >> 46 for k in (4, 5, 6) if len(word) > k}
    return out


def plain_chain(x, labels, fold):
    """Two logistic regressions on dense rows, the second with the first's out-of-fold probabilities: (p of all rows, thresholds)."""
    n, outside, inside, thresholds = len(x), np.zeros((len(x), 0)), np.zeros((len(x), 0)), []
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -35, 35)))
    logit = lambda p: np.log(np.clip(p, 1e-4, 1 - 1e-4) / (1 - np.clip(p, 1e-4, 1 - 1e-4)))

    def train(rows, extra, y):
        have, both, m, pos = rows.sum(0), rows[y == 1].sum(0), len(y), y.sum()
        chi = m * (both * m - have * pos) ** 2 / np.maximum(have * (m - have) * pos * (m - pos), 1e-9)
        a = np.column_stack([rows * (chi >= 12.0), extra, np.ones(m)])
        w = np.zeros(a.shape[1])
        w[-1] = logit(y.mean())
        decay = np.full(len(w), 2e-4)
        decay[-1] = 0
        m1, m2 = np.zeros(len(w)), np.zeros(len(w))
        for t in range(1, 301):
            g = a.T @ (sigmoid(a @ w) - y) / m + decay * w
            m1, m2 = 0.9 * m1 + 0.1 * g, 0.999 * m2 + 0.001 * g * g
            w = w - 0.08 * (m1 / (1 - 0.9**t)) / (np.sqrt(m2 / (1 - 0.999**t)) + 1e-9)
        return w

    for k in range(labels.shape[1]):
        y, p = labels[:, k].astype(float), np.full(n, labels[:, k].mean())
        for f in range(4):
            test = fold == f
            if test.any() and y[~test].min() < y[~test].max():
                w = train(x[~test], logit(outside[~test]), y[~test])
                p[test] = sigmoid(np.column_stack([x, logit(outside), np.ones(n)])[test] @ w)
        whole = train(x, logit(outside), y)
        ranked = np.sort(p)[::-1]
        hits = np.cumsum(y[np.argsort(-p, kind="stable")])
        best = int((2 * hits / (np.arange(1, n + 1) + y.sum())).argmax())
        thresholds.append((ranked[best] + ranked[min(best + 1, n - 1)]) / 2)
        outside = np.column_stack([outside, p])
        yield whole
    yield thresholds


def test_the_toxicity_query_is_a_plain_classifier_chain(spark):
    from nearfield.llm.queries import op1_toxicity_chain

    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()}
    labels = spark.read.parquet(f"{SMALL}/labels.parquet").where("doc_id is not null").selectExpr("doc_id", "quality", "toxic", "xxhash64(doc_id, 7) AS spot").dropna().distinct().collect()
    known = sorted((r.spot, r.doc_id, int(r.quality == 0), int(r.toxic == 1)) for r in labels if r.doc_id in docs)
    words = {d: plain_features(t) for d, t in docs.items()}
    assert all(set(toxicity.features(docs[d]).tolist()) == words[d] for d in docs)
    seen = Counter(f for _, d, *_ in known for f in words[d])
    columns = [f for f, n in seen.items() if n >= toxicity.LEAST_ROWS]
    rows = lambda ids: np.array([[f in words[d] for f in columns] for d in ids], float)
    first, second, thresholds = plain_chain(rows([k[1] for k in known]), np.array([k[2:] for k in known]), np.array([(k[0] >> 24) % 4 for k in known]))
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -35, 35)))
    ids, ones = sorted(docs), np.ones(len(docs))
    p1 = sigmoid(np.column_stack([rows(ids), ones]) @ first)
    clipped = np.clip(p1, 1e-4, 1 - 1e-4)
    p2 = sigmoid(np.column_stack([rows(ids), np.log(clipped / (1 - clipped)), ones]) @ second)
    got = {r.doc_id: r for r in op1_toxicity_chain(spark, SMALL).collect()}
    assert [got[d].p_low_quality for d in ids] == pytest.approx(p1.tolist(), abs=1e-4)
    assert [got[d].p_toxic for d in ids] == pytest.approx(p2.tolist(), abs=1e-4)
    assert [got[d].toxic for d in ids] == (p2 >= thresholds[1]).tolist()


def test_later_models_use_earlier_categories():
    draw = np.random.default_rng(0)
    rows = [np.unique(draw.integers(0, 60, 12)).astype(np.int32) for _ in range(800)]
    first = np.array([int(5 in r) for r in rows])
    chain = toxicity.fit_chain(rows, np.stack([first, first], axis=1), ["a", "b"], np.arange(800) % 4)
    assert chain.earlier[0].size == 0 and chain.earlier[1].size == 1 and chain.earlier[1][0] > 0.1
    p = chain.probabilities(rows)
    assert ((p[:, 1] > chain.threshold[1]) == first).mean() > 0.99


def test_toxicity_of_odd_documents(spark):
    docs = odd_docs(spark).selectExpr("*", "0 as p_toxic")
    nothing = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = toxicity.predict(docs, toxicity.learn(docs, nothing, CATEGORIES))
    assert out.columns == [c for c in docs.columns if c != "p_toxic"] + ["p_low_quality", "p_toxic", "is_low_quality", "is_toxic"]
    assert out.count() == docs.count() and out.where("is_toxic").count() == 0
    one = spark.createDataFrame([(1, 1, 0), (2, None, 1), (None, 1, 1), (3, 0, 0)], "doc_id long, quality int, toxic int")
    assert toxicity.predict(empty(spark), toxicity.learn(docs, one, CATEGORIES)).count() == 0
