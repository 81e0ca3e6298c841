"""Token-id files: one id array for many documents, with Elias-Fano document boundaries.

A file holds documents in ascending doc_id order (null first): a header, the boundaries of the documents in the id
array and the doc_ids as two Elias-Fano lists, then all ids as little-endian unsigned integers of two bytes, or four
if the vocabulary needs them. Files are named by partition and number, so their name order is doc_id order too.
"""

from __future__ import annotations

import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .elias_fano import EliasFano
from .shared import cut, plain, remove_folder, shared_folder, tidy

MAGIC = b"NFTOKEF1"
_HEAD = struct.Struct("<8sIIQQQq")
#: Ids in a file, but for one larger document.
FILE_IDS = 1 << 23
#: Bytes of words and ids that a worker remembers before it starts anew, and of the longest word it remembers.
MEMO_BYTES, LONG_WORD = 144 << 20, 64
#: Bytes of texts that are taken apart at a time.
STEP = 1 << 20


#: UTF-8 bytes of ASCII and of U+00C0 to U+00FF; its letters are all of the latter but U+00D7 and U+00F7.
_LATIN = bytes(range(128)) + b"\xc3" + bytes(range(0x80, 0xC0))
#: What a remembered entry takes beside its bytes, about.
_ENTRY = 160


class WordEncoder:
    """The tokenizers library over whole texts, with a memo of words.

    For a tokenizer that drops white space, lower-cases, and takes contractions, runs of letters, single digits and
    runs of other characters apart: a text's ids are those of its words in order. Texts of ASCII and Latin letters
    are cut at white space, then taken apart here by the same rule, and new words go to the library many at a time,
    where the ids that end a word show which are whose; all other texts, and those that hold the string of an added
    token, go to it whole. ``tests/llm`` holds both against encoding whole texts.
    """

    WORDS = re.compile(rb"'s|'t|'re|'ve|'m|'ll|'d|(?:[a-z]+|(?:\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+)+|[0-9]|[^\sa-z0-9\xc3\x80-\xbf]+")

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        size = self.tokenizer.get_vocab_size()
        suffix = getattr(self.tokenizer.model, "end_of_word_suffix", None)
        self.ends = np.zeros(size, bool)
        if suffix:
            self.ends[[i for t, i in self.tokenizer.get_vocab().items() if t.endswith(suffix)]] = True
        self.added = [t.content.encode().lower() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.kind = np.dtype("<u4" if size > 1 << 16 else "<u2")
        #: Ids of single words and of what white space sets apart ("word," and the like).
        self.memo: dict[bytes, bytes] = {}
        self.held = 0

    def _ids(self, text: str) -> np.ndarray:
        return np.asarray(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.kind)

    def plain(self, lower: bytes) -> bool:
        """Whether the words of a lower-cased text are those of ``WORDS``."""
        return not lower.translate(None, _LATIN) and b"\xc3\x97" not in lower and b"\xc3\xb7" not in lower and not any(t in lower for t in self.added)

    def _words(self, words: list[bytes]) -> dict[bytes, bytes]:
        """The ids of words that are one word each."""
        width, found = self.kind.itemsize, {}
        for at in range(0, len(words), 4096):
            some = words[at : at + 4096]
            ids = self._ids(b" ".join(some).decode())
            ends = (np.flatnonzero(self.ends[ids]) + 1) * width
            if len(ends) == len(some):
                data, ends = ids.tobytes(), ends.tolist()
                found.update(zip(some, [data[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)], strict=True))
            else:  # a tokenizer without ends of words
                found.update((w, self._ids(w.decode()).tobytes()) for w in some)
        return found

    def _keep(self, found: dict[bytes, bytes]) -> None:
        short = found if len(max(found, key=len, default=b"")) <= LONG_WORD else {w: ids for w, ids in found.items() if len(w) <= LONG_WORD}
        self.memo.update(short)
        self.held += sum(map(len, short)) + sum(map(len, short.values())) + _ENTRY * len(short)

    def _look_up(self, chunks: list[list[bytes]]) -> dict[bytes, bytes]:
        """The ids of all chunks; long ones are not remembered."""
        if self.held > MEMO_BYTES:
            self.memo, self.held = {}, 0
        new = set().union(*chunks).difference(self.memo)
        if not new:
            return self.memo
        split = {c: w for c in new if len(w := self.WORDS.findall(c)) != 1}
        single = new.difference(split)
        found = self._words(list(single.union(*split.values()).difference(self.memo)))
        self._keep(found)
        found = _Both(found, self.memo)
        joined = {c: b"".join([found[x] for x in w]) for c, w in split.items()}
        self._keep(joined)
        found.update(joined)
        return self.memo if len(max(new, key=len)) <= LONG_WORD else found

    def encode(self, texts: list[bytes]) -> Iterator[bytes]:
        """The packed ids of each text."""
        at = 0
        while at < len(texts):
            some, size = [], 0
            while at < len(texts) and (not some or len(some) < 256 and size + len(texts[at]) <= STEP):
                size += len(texts[at])
                some.append(texts[at])
                at += 1
            if size > STEP:  # one long text, a stretch at a time
                yield self._long(some[0])
                continue
            lower = [t.lower() for t in some]
            chunks = [t.split() if self.plain(t) else None for t in lower]
            ids = self._look_up([c for c in chunks if c])
            for c, t in zip(chunks, some, strict=True):
                yield b"".join(map(ids.__getitem__, c)) if c is not None else self._ids(t.decode("utf-8", "replace")).tobytes()

    def _long(self, text: bytes) -> bytes:
        lower = text.lower()
        if not self.plain(lower):
            return self._ids(text.decode("utf-8", "replace")).tobytes()
        out, at = [], 0
        while at < len(lower):
            space = _SPACE.search(lower, at + STEP)
            end = space.start() if space else len(lower)
            chunks = lower[at:end].split()
            out.extend(map(self._look_up([chunks]).__getitem__, chunks))
            at = end
        return b"".join(out)


_SPACE = re.compile(rb"[ \t\n\r\x0b\x0c]")


class _Both(dict):
    """A small mapping before a large one."""

    def __init__(self, few: dict, many: dict):
        super().__init__(few)
        self.many = many

    def __missing__(self, key):
        return self.many[key]


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """This worker's encoder for the file."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def pack(doc_ids: list[int | None], ids: list[bytes], kind: np.dtype) -> bytes:
    """A file's bytes; ``doc_ids`` ascending, nulls first."""
    nulls = sum(d is None for d in doc_ids)
    known = np.array(doc_ids[nulls:], np.int64)
    first = int(known[0]) if known.size else 0
    counts = [len(b) // kind.itemsize for b in ids]
    ends = EliasFano.of(np.cumsum([0, *counts]))
    numbers = EliasFano.of((known.astype(np.uint64) - np.uint64(first % 2**64)))
    head = _HEAD.pack(MAGIC, 1, kind.itemsize, len(doc_ids), nulls, sum(counts), first)
    return b"".join([head, ends.to_bytes(), numbers.to_bytes(), *ids])


class TokenFile:
    """Reads one file's bytes; ``document(i)`` reaches a document by select, without a table of offsets."""

    def __init__(self, data):
        magic, version, width, self.n_docs, self.n_null, self.n_ids, self.first = _HEAD.unpack_from(data, 0)
        if magic != MAGIC or version != 1:
            raise ValueError("not a token file of this format")
        self.ends, at = EliasFano.from_bytes(data, _HEAD.size)
        self.numbers, at = EliasFano.from_bytes(data, at)
        self.ids = np.frombuffer(data, f"<u{width}", self.n_ids, at)

    def document(self, i: int) -> np.ndarray:
        return self.ids[self.ends.select(i) : self.ends.select(i + 1)]

    def doc_ids(self) -> list[int | None]:
        known = (self.numbers.all().astype(np.uint64) + np.uint64(self.first % 2**64)).astype(np.int64)
        return [None] * self.n_null + known.tolist()


def put(folder: str, name: str, data: bytes) -> None:
    """Write a file so that it is there whole or not at all, also when a task runs twice."""
    store, path = fs.FileSystem.from_uri(folder)
    store.create_dir(path, recursive=True)
    with store.open_output_stream(part := f"{path}/_{name}.{uuid.uuid4().hex}") as out:
        out.write(data)
    store.move(part, f"{path}/{name}")


def write_token_files(docs: DataFrame, tokenizer: str, folder: str, end_id: int | None = 2, file_ids: int = FILE_IDS) -> DataFrame:
    """Encode every whole text and write the files; returns a row (file, n_docs, n_ids) for each.

    Null text is empty text: only the end id. Null doc_ids come first; rows that share a doc_id keep one order of
    their own (by the text's hash). Other columns are ignored. An empty table writes no file.
    """

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(tokenizer)
        end = b"" if end_id is None else np.array([end_id], own.kind).tobytes()
        part, number, held = TaskContext.get().partitionId(), 0, 0
        doc_ids: list[int | None] = []
        ids: list[bytes] = []

        def flush() -> pa.RecordBatch:
            nonlocal number, held
            name = f"{part:08d}-{number:08d}.tef"
            put(folder, name, pack(doc_ids, ids, own.kind))
            row = pa.RecordBatch.from_pydict({"file": [name], "n_docs": pa.array([len(ids)], pa.int64()), "n_ids": pa.array([held], pa.int64())})
            doc_ids.clear()
            ids.clear()
            number, held = number + 1, 0
            return row

        for b in batches:
            texts = b.column(1).cast(pa.binary()).to_pylist()
            for d, packed in zip(b.column(0).to_pylist(), own.encode(texts), strict=True):
                doc_ids.append(d)
                ids.append(packed + end)
                held += len(ids[-1]) // own.kind.itemsize
                if held >= file_ids:
                    yield flush()
        if ids:
            yield flush()

    rows = docs.select("doc_id", plain("text").alias("text"))
    ordered = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"), "text")
    return cut(ordered.mapInArrow(tidy(write), "file string, n_docs long, n_ids long"))


def read_token_files(spark, folder: str, files: DataFrame) -> DataFrame:
    """Per document of the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32.

    The crc is that of all the document's ids as little-endian unsigned 32-bit integers.
    """

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, data in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                f = TokenFile(data.as_buffer())
                ends = f.ends.all()
                crc = [zlib.crc32(f.ids[s:e].astype("<u4")) for s, e in zip(ends[:-1], ends[1:], strict=True)]
                yield pa.RecordBatch.from_pydict(
                    {
                        "file": [path.rpartition("/")[2]] * f.n_docs,
                        "doc_id": pa.array(f.doc_ids(), pa.int64()),
                        "place": pa.array(ends[:-1], pa.int64()),
                        "n_tokens": pa.array(np.diff(ends), pa.int64()),
                        "ids_crc32": pa.array(crc, pa.int64()),
                    }
                )

    content = spark.read.format("binaryFile").option("pathGlobFilter", "*.tef").load(folder).select("path", "content")
    found = content.mapInArrow(tidy(read), "file string, doc_id long, place long, n_tokens long, ids_crc32 long")
    before = F.coalesce(F.sum("n_ids").over(W.orderBy("file").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    starts = files.select("file", before.alias("before"))
    return found.join(starts, "file").select("doc_id", (F.col("before") + F.col("place")).alias("start"), "n_tokens", "ids_crc32")


def token_table(docs: DataFrame, tokenizer: str, end_id: int | None = 2, folder: str | None = None) -> DataFrame:
    """Write the documents' ids to files and read them back; see ``write_token_files`` and ``read_token_files``.

    Without ``folder`` the files are a passing step: the rows read are cut and the files removed.
    """
    spark = docs.sparkSession
    own = folder or shared_folder(spark, "token-files")
    files = write_token_files(docs, tokenizer, own, end_id)
    if files.isEmpty():
        return spark.createDataFrame([], "doc_id long, start long, n_tokens long, ids_crc32 long")
    found = read_token_files(spark, own, files)
    if folder is None:
        found = cut(found)
        remove_folder(spark, own)
    return found
