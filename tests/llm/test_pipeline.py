"""The pipeline's stages, each against a plain version on its own input."""

import hashlib
import struct
import zlib
from collections import Counter, defaultdict

import corpus_pipeline
from nearfield.llm import mixing, pieces
from nearfield.llm.queries import ORACLES, QUERIES, tokenizer_path
from tests.llm.test_operators import SMALL, odd_docs, plain_components, plain_dedup, shingles


def test_every_stage_against_a_plain_version(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{SMALL}/labels.parquet").collect()}
    for number, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = docs.collect()
        out = stage(spark, docs, SMALL)
        out.write.parquet(f"{tmp_path}/{number}")
        docs = spark.read.parquet(f"{tmp_path}/{number}")
        after = docs.collect()
        if name != "pieces":
            assert docs.columns == corpus_pipeline.COLUMNS
        if name == "toxicity":
            kept = {r.doc_id for r in after}
            clean = [r.doc_id for r in before if labels.get(r.doc_id) == 0]
            assert sum(d in kept for d in clean) >= 0.95 * len(clean)
            assert set(after) <= set(before)
        elif name == "line_dedup":
            got = Counter((r.doc_id, hashlib.sha256(r.text.encode()).hexdigest()) for r in after)
            assert got == Counter((d, s) for d, _, _, s in plain_dedup([(r.doc_id, r.text) for r in before]).elements())
            assert all(r.n_chars == len(r.text) for r in after)
        elif name == "jaccard_join":
            component = plain_components({r.doc_id: shingles(r.text, 5) for r in before}, 80)
            assert Counter(after) == Counter(r for r in before if component[r.doc_id] == r.doc_id)
        elif name == "mixing":
            taken = {r.doc_id: r for r in mixing.mix(spark.createDataFrame(before)).collect()}
            want = Counter()
            for r in before:
                t = taken[r.doc_id]
                want[r] += (2 * t.taken + t.size) // (2 * t.size) if t.size else 0
            assert Counter(after) == +want
            words, target = defaultdict(int), {}
            for r in after:
                words[r.source] += taken[r.doc_id].size
            for t in taken.values():
                target[t.source] = t.target
            assert abs(sum(words.values()) / sum(target.values()) - 1) < 0.2
        else:
            m = pieces.model(tokenizer_path("piece_bpe_32k.model"))
            want = Counter()
            for r in before:
                ids = m.encode(r.text)
                want[(r.doc_id, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids)), True)] += 1
            assert Counter((r.doc_id, r.n_ids, r.ids_crc32, r.round_trip) for r in after) == want


def test_every_stage_takes_odd_documents(spark):
    whole = odd_docs(spark).select(*corpus_pipeline.COLUMNS)
    for docs in (whole, whole.limit(0)):
        n = docs.count()
        for name, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, SMALL)
            rows = docs.collect()
            if name == "toxicity":
                assert len(rows) <= n
            if name == "line_dedup" and n:
                assert sum(r.text is not None and "shared by several" in r.text.lower() for r in rows) == sum(r.doc_id == 3 for r in rows)
            if name == "jaccard_join" and n:
                assert any(r.doc_id is None for r in rows) and any(r.text is None for r in rows)
            if name == "mixing":
                assert all((r.text or "").split() for r in rows)
            if name != "pieces":
                docs = spark.createDataFrame(rows, docs.schema)
                assert docs.columns == corpus_pipeline.COLUMNS
            else:
                assert all(r.round_trip or "\u2581" in str(r) or r.doc_id == 10 for r in rows) and (n > 0) == bool(rows)


def test_run_applies_all_stages_and_repeats(spark):
    first = Counter((r.doc_id, r.ids_crc32) for r in corpus_pipeline.run(spark, SMALL).collect())
    assert first == Counter((r.doc_id, r.ids_crc32) for r in corpus_pipeline.run(spark, SMALL).collect())
    assert len(first) > 80


def test_a_query_for_each_operator():
    assert [n.split("_")[0] for n in QUERIES][:10] == [f"op{i}" for i in range(1, 11)] and "pipeline" in QUERIES
    assert set(ORACLES) <= set(QUERIES)
