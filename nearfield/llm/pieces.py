"""SentencePiece encoding and decoding: a unigram Viterbi over a double-array trie of pieces with log scores.

The pieces come from a public vocabulary file. White space is marked by U+2581 and a marker is put before the text;
characters without a piece become their UTF-8 bytes' pieces. No piece has a marker after another character, so the
best path of a text is that of its stretches between markers, and a worker remembers those.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .shared import plain, tidy

MARK = "▁".encode()
#: Bytes of stretches and ids that a worker remembers, and of the longest stretch it remembers.
MEMO_BYTES, LONG = 48 << 20, 64
#: What a remembered entry takes beside its bytes, about.
_ENTRY = 160
#: Texts, and bytes of texts, that are solved at a time.
TEXTS, STEP = 256, 1 << 20
#: What a character without a piece scores below the worst piece.
UNKNOWN_PENALTY = 10.0
#: Stretches of at most so many bytes are laid out in arrays and solved together, so many at a time.
SHORT, TOGETHER = 48, 16_384


class DoubleArray:
    """A trie over byte strings: the child of state s by byte c is base[s] + c if check there is s."""

    def __init__(self, keys: list[bytes]):
        trie: dict = {}
        for number, key in enumerate(keys):
            node = trie
            for c in key:
                node = node.setdefault(c, {})
            node[-1] = number
        size = 1 << 16
        base, check, value = [0] * size, [-1] * size, [-1] * size
        used = bytearray(size)
        used[0] = 1
        start, queue = 1, [(0, trie)]
        while queue:
            nodes, queue = queue, []
            for state, node in nodes:
                value[state] = node.get(-1, -1)
                children = sorted(c for c in node if c >= 0)
                if not children:
                    base[state] = 1
                    continue
                while used[start]:
                    start += 1
                at = max(start, children[0] + 1)
                while True:
                    at = used.find(0, at)
                    if at < 0 or at + 600 > len(used):
                        grow = len(used)
                        for a, fill in ((base, 0), (check, -1), (value, -1)):
                            a.extend([fill] * grow)
                        used.extend(bytes(grow))
                        at = max(at, 0) or start
                        continue
                    b = at - children[0]
                    if b > 0 and all(not used[b + c] for c in children):
                        break
                    at += 1
                base[state] = b
                for c in children:
                    used[b + c], check[b + c] = 1, state
                    queue.append((b + c, node[c]))
        self.base, self.check, self.value = (np.array(a, np.int32) for a in (base, check, value))


class PieceModel:
    """``scores``: "rank" takes -ln(rank + 2.7) by the file's order (a Zipf law of frequencies); "file" the file's own."""

    def __init__(self, path: str, scores: str = "rank"):
        from sentencepiece import SentencePieceProcessor

        read = SentencePieceProcessor(model_file=path)
        n = read.get_piece_size()
        names = [read.id_to_piece(i) for i in range(n)]
        self.unk = read.unk_id()
        self.byte_id = np.full(256, self.unk, np.int64)
        self.text = [b""] * n
        own = []
        for i, name in enumerate(names):
            if read.is_byte(i):
                b = int(name[1:-1], 16)
                self.byte_id[b], self.text[i] = i, bytes([b])
            elif not (read.is_control(i) or read.is_unknown(i) or read.is_unused(i)):
                self.text[i] = name.encode()
                own.append(i)
        self.score = np.zeros(n)
        for rank, i in enumerate(own):
            self.score[i] = read.get_score(i) if scores == "file" else -np.log(rank + 2.7)
        self.unknown = float(self.score[own].min()) - UNKNOWN_PENALTY
        keys = [self.text[i] for i in own]
        if any(MARK in k.lstrip(MARK) and k.replace(MARK, b"") and not k.rsplit(MARK, 1)[0].replace(MARK, b"") == b"" for k in keys):
            raise ValueError("a piece has a white-space marker after another character")
        cuts = b"" if any(b"\n" in k for k in keys) else b"\n"
        self.stretch = re.compile(rb"(?:\xe2\x96\x81)+(?:(?!\xe2\x96\x81)[^%s])*|%s(?:(?!\xe2\x96\x81)[^%s])+" % (cuts or b"\xff", cuts + b"+|" if cuts else b"", cuts or b"\xff"), re.S)
        trie = DoubleArray(keys)
        self.base, self.check = trie.base, trie.check
        self.value = np.where(trie.value >= 0, np.array(own, np.int32)[trie.value], -1)
        self.lists: tuple | None = None
        self.kind = np.dtype("<u2" if n <= 1 << 16 else "<u4")
        self.bytes_of = np.array([len(t) for t in self.text])
        self.is_byte = np.zeros(n, bool)
        self.is_byte[self.byte_id[self.byte_id != self.unk]] = True
        self.memo: dict[bytes, bytes] = {}
        self.held = 0

    def __getstate__(self):
        return self.__dict__ | {"memo": {}, "held": 0, "lists": None}

    def _one(self, s: bytes) -> list[int]:
        """Best path of one stretch, state by state."""
        if self.lists is None:
            self.lists = tuple(a.tolist() for a in (self.base, self.check, self.value, self.score))
        base, check, value, score = self.lists
        n = len(s)
        best, back = [-np.inf] * (n + 1), [(0, 0)] * (n + 1)
        best[0] = 0.0
        at = 0
        while at < n:
            lead = s[at]
            width = min(1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4, n - at)
            here, state, single = best[at], 0, False
            for to in range(at, n):
                nxt = base[state] + s[to]
                if check[nxt] != state:
                    break
                state = nxt
                if (v := value[state]) >= 0:
                    single |= to + 1 == at + width
                    if here + score[v] > best[to + 1]:
                        best[to + 1], back[to + 1] = here + score[v], (at, v)
            if not single and here + self.unknown > best[at + width]:
                best[at + width], back[at + width] = here + self.unknown, (at, -1)
            at += width
        out: list[int] = []
        at = n
        while at:
            before, v = back[at]
            out.extend([v] if v >= 0 else self.byte_id[list(s[before:at])][::-1].tolist())
            at = before
        return out[::-1]

    def _many(self, all_of: list[bytes]) -> list[list[int]]:
        """Best paths of short stretches, one step of all of them at a time."""
        w = len(all_of)
        length = np.array([len(s) for s in all_of])
        most = int(length.max())
        data = np.frombuffer(b"".join(s.ljust(most, b"\0") for s in all_of), np.uint8).reshape(w, most).astype(np.int32)
        width = np.where(data < 0x80, 1, np.where(data < 0xC0, 0, np.where(data < 0xE0, 2, np.where(data < 0xF0, 3, 4))))
        best = np.full((w, most + 1), -np.inf)
        best[:, 0] = 0
        back = np.zeros((w, most + 1), np.int32)
        piece = np.full((w, most + 1), -1, np.int32)
        for at in range(most):
            rows = np.flatnonzero((length > at) & (width[:, at] > 0))
            first, here = rows, best[rows, at]
            single = np.zeros(w, bool)
            state, to = np.zeros(len(rows), np.int32), at
            while len(rows):
                nxt = self.base[state] + data[rows, to]
                ok = self.check[nxt] == state
                rows, state, here = rows[ok], nxt[ok], here[ok]
                to += 1
                v = self.value[state]
                hit = v >= 0
                r, p, total = rows[hit], v[hit], here[hit] + self.score[v[hit]]
                single[r] |= width[r, at] == to - at
                up = total > best[r, to]
                r, p = r[up], p[up]
                best[r, to], piece[r, to], back[r, to] = total[up], p, at
                more = length[rows] > to
                if not more.all():
                    rows, state, here = rows[more], state[more], here[more]
            r = first[~single[first]]
            if len(r):
                end = np.minimum(at + width[r, at], length[r])
                total = best[r, at] + self.unknown
                up = total > best[r, end]
                r, end = r[up], end[up]
                best[r, end], piece[r, end], back[r, end] = total[up], -1, at
        out = []
        for s, n, b, p in zip(all_of, length.tolist(), back.tolist(), piece.tolist(), strict=True):
            ids: list[int] = []
            while n:
                ids.extend([p[n]] if p[n] >= 0 else self.byte_id[list(s[b[n] : n])][::-1].tolist())
                n = b[n]
            out.append(ids[::-1])
        return out

    def solve(self, stretches: list[bytes]) -> list[list[int]]:
        short = sorted((s for s in stretches if len(s) <= SHORT), key=len)  # like lengths together
        found: dict[bytes, list[int]] = {}
        for at in range(0, len(short), TOGETHER):
            some = short[at : at + TOGETHER]
            found.update(zip(some, self._many(some), strict=True))
        return [found[s] if len(s) <= SHORT else self._one(s) for s in stretches]

    def encode_packed(self, texts: list[bytes]) -> Iterator[bytes]:
        """The ids of each UTF-8 text, packed; nothing for an empty text."""
        at = 0
        while at < len(texts):
            some, size = [], 0
            while at < len(texts) and (not some or len(some) < TEXTS and size + len(texts[at]) <= STEP):
                size += len(texts[at])
                some.append(texts[at])
                at += 1
            split = [self.stretch.findall(MARK + t.replace(b" ", MARK)) if t else [] for t in some]
            if self.held > MEMO_BYTES:
                self.memo, self.held = {}, 0
            memo = self.memo
            new = list(set().union(*split).difference(memo))
            if new:
                found = dict(zip(new, (np.array(ids, self.kind).tobytes() for ids in self.solve(new)), strict=True))
                short = found if len(max(new, key=len)) <= LONG else {s: ids for s, ids in found.items() if len(s) <= LONG}
                memo.update(short)
                self.held += sum(map(len, short)) + sum(map(len, short.values())) + _ENTRY * len(short)
                if len(short) < len(found):  # long stretches are not remembered
                    for ss in split:
                        yield b"".join([found[s] if s in found else memo[s] for s in ss])
                    continue
            for ss in split:
                yield b"".join(map(memo.__getitem__, ss))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(next(self.encode_packed([text.encode()])), self.kind).tolist()

    def decode(self, ids) -> bytes:
        """UTF-8 bytes of a text: markers as spaces, without the one before the text."""
        data = b"".join([self.text[i] for i in ids])
        return data.removeprefix(MARK).replace(MARK, b" ")


_models: dict[tuple[str, str], PieceModel] = {}


def model(path: str, scores: str = "rank") -> PieceModel:
    """This process's model of the file."""
    if (path, scores) not in _models:
        _models[path, scores] = PieceModel(path, scores)
    return _models[path, scores]


def encode_pieces(docs: DataFrame, path: str, scores: str = "rank", with_ids: bool = True) -> DataFrame:
    """Per row: doc_id, ids (packed little-endian, of the model's width), n_ids, n_byte_ids, ids_crc32, round_trip.

    ``ids_crc32`` is that of the ids as little-endian unsigned 32-bit integers; ``round_trip`` tells whether decoding
    gives the text back (not for texts that hold the marker itself). Null text is encoded as empty text: no ids. Rows
    that share a doc_id are encoded each; other columns are ignored. The vocabulary file must be on every executor.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path, scores)
        for b in batches:
            texts = b.column(1).cast(pa.binary()).to_pylist()
            packed = list(m.encode_packed(texts))
            arrays = [np.frombuffer(p, m.kind) for p in packed]
            columns = {
                "doc_id": b.column(0),
                "ids": pa.array(packed, pa.binary()),
                "n_ids": pa.array([a.size for a in arrays], pa.int64()),
                "n_byte_ids": pa.array([int(m.is_byte[a].sum()) for a in arrays], pa.int64()),
                "ids_crc32": pa.array([zlib.crc32(a.astype("<u4")) for a in arrays], pa.int64()),
                "round_trip": pa.array([m.decode(a.tolist()) == t for a, t in zip(arrays, texts, strict=True)], pa.bool_()),
            }
            if not with_ids:
                del columns["ids"]
            yield pa.RecordBatch.from_pydict(columns)

    ids = "ids binary, " if with_ids else ""
    return docs.select("doc_id", plain("text").alias("text")).mapInArrow(tidy(run), f"doc_id long, {ids}n_ids long, n_byte_ids long, ids_crc32 long, round_trip boolean")


def decode_pieces(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids) of ``encode_pieces``; null ids give null text."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path)
        for b in batches:
            texts = [None if p is None else m.decode(np.frombuffer(p, m.kind).tolist()).decode("utf-8", "replace") for p in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(tidy(run), "doc_id long, text string")
