"""Packed word sequences and the sets of documents that share them, against plain Python."""

from collections import Counter, defaultdict

import pyarrow as pa
import pytest

from nearfield.operators import workloads

TEXTS = [
    (1, "a b c d e f g"), (2, " a\tb c\n d e\x0bf "), (3, "a b c d e"), (4, "a b"), (5, "a  b\r"), (6, ""), (7, " \n"), (8, None), (None, "a b c d e"),
    (9, "ab c d e f"), (10, "a bc d e f"), (11, "é ü 日本 d e f"), (12, "é ü 日本 d e f"), (-3, "a b c d e a b c d e"), (2, "a b c d e f"), (13, "a b c d e f"), (14, "A b c d e"),
]


def plain(texts, words=5):
    of = defaultdict(set)
    for doc, text in texts:
        if doc is not None and text is not None:
            for c in "\t\n\x0b\f\r":
                text = text.replace(c, " ")
            w = [x for x in text.split(" ") if x] or [""]
            for i in range(max(len(w) - words + 1, 1)):
                of[" ".join(w[i : i + words])].add(doc)
    return Counter(tuple(sorted(s)) for s in of.values() if len(s) > 1)


@pytest.mark.parametrize("packed", [2_000_000, 4])
def test_shared_sets(spark, tmp_path, monkeypatch, packed):
    monkeypatch.setattr(workloads, "PACKED", packed)
    texts = TEXTS + [(100 + k, "one line that all have, and more " + str(k % 40)) for k in range(300)]
    spark.createDataFrame(texts, "doc_id long, text string").repartition(7).write.parquet(f"{tmp_path}/documents.parquet")
    got = {tuple(r.docs): r.times for r in workloads.shared_sets(spark, str(tmp_path)).collect()}
    assert got == dict(plain(texts))


def test_a_sequence_takes_few_bytes_of_the_shuffle(spark, tmp_path):
    """The packed rows of all sequences, which are what is shuffled, compress below 10 bytes a sequence."""
    import random

    r = random.Random(1)
    words = ["".join(r.choices("abcdefghij", k=7)) for _ in range(5000)]
    texts = [" ".join(r.choices(words, k=400)) for _ in range(500)]
    h, check, doc = workloads.hashed_sequences(pa.array(range(500)).to_numpy(), pa.array(texts))
    assert len(h) == 500 * 396 == len(set(zip(h.tolist(), doc.tolist(), strict=True)))
    packed = workloads.packed_planes(h, check, doc)
    assert len(pa.compress(packed, codec="lz4_raw", asbytes=True)) < 10 * len(h)
