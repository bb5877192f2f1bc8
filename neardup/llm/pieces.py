"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie of pieces with log scores.

The model file (pieces, scores, kinds, normaliser flags) is read on the driver; its trie, of at most the
vocabulary's size, is broadcast. Spaces become whitespace markers and a marker is put in front. The best
segmentation has the largest sum of scores; of equal ones, the one whose last piece is longer. A character
that no piece covers costs the smallest score less ``UNKNOWN`` and is written as its bytes.

Where no piece has a marker after another character (checked on reading), the best segmentation of a text is
that of its parts, split before each run of markers and around characters that no piece holds; each distinct
part is solved once a worker, in a cache of bounded size. Decoding joins pieces, bytes as UTF-8, markers as
spaces, and drops the marker in front: every text comes back exactly. A marker character in the text itself
is written as bytes, so it is not taken for a space.

Defined cases: a null text counts as empty and has no pieces; repeated rows are encoded alike; texts of any
length are encoded whole; extra columns are ignored; an empty table gives an empty result. Models with a
character map, without byte pieces, or that drop extra white space are refused.
"""

from __future__ import annotations

import re
import struct

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.batches import by_row

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK, UNKNOWN, CACHE = "▁", 10.0, 200_000
#: Stands for a marker character of the text itself; no text and no piece can hold a lone surrogate.
_LITERAL = "\udfff"


def _varint(data: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = data[at]
        at += 1
        value |= (byte & 127) << shift
        shift += 7
        if byte < 128:
            return value, at


def _fields(data: bytes):
    at = 0
    while at < len(data):
        key, at = _varint(data, at)
        kind = key & 7
        if kind == 0:
            value, at = _varint(data, at)
        else:
            size = {1: 8, 5: 4}.get(kind)
            if size is None:
                size, at = _varint(data, at)
            value, at = data[at : at + size], at + size
        yield key >> 3, value


def read_model(data: bytes) -> tuple[list[tuple[str, float, int]], bool]:
    """Pieces ``(text, score, kind)`` by id, and whether a marker goes in front."""
    pieces, prefix = [], True
    for no, value in _fields(data):
        if no == 1:
            f = dict(_fields(value))
            pieces.append((f[1].decode(), struct.unpack("<f", f[2])[0] if 2 in f else 0.0, f.get(3, 1)))
        elif no == 3:
            f = dict(_fields(value))
            if f.get(2) or f.get(4, 1) or not f.get(5, 1):
                raise ValueError("only models without a character map, that keep white space and escape it")
            prefix = bool(f.get(3, 1))
    return pieces, prefix


class DoubleArray:
    """A trie over bytes in two arrays: node ``s`` goes to ``base[s] + byte + 1`` where ``check`` says ``s``."""

    def __init__(self, keys: list[tuple[bytes, int]]):
        keys = sorted(keys)
        size = 1 << 12
        self.base, self.check = np.zeros(size, np.int32), np.full(size, -1, np.int32)
        self.value = np.full(size, -1, np.int32)
        self.check[0] = 0
        todo, low = [(0, 0, len(keys), 0)], 1
        while todo:
            node, lo, hi, depth = todo.pop()
            if lo < hi and len(keys[lo][0]) == depth:
                self.value[node] = keys[lo][1]
                lo += 1
            if lo == hi:
                continue
            groups, start = [], lo
            for i in range(lo + 1, hi + 1):
                if i == hi or keys[i][0][depth] != keys[start][0][depth]:
                    groups.append((keys[start][0][depth] + 1, start, i))
                    start = i
            offsets = np.array([g[0] for g in groups])
            while low < len(self.check) and self.check[low] >= 0:
                low += 1
            place, window = max(1, low - int(offsets[0])), 64
            while True:  # the first place, in windows of doubling length, where every child's cell is free
                while place + window + 258 >= len(self.check):
                    more = len(self.check)
                    self.base = np.append(self.base, np.zeros(more, np.int32))
                    self.check = np.append(self.check, np.full(more, -1, np.int32))
                    self.value = np.append(self.value, np.full(more, -1, np.int32))
                free = np.ones(window, bool)
                for o in offsets:
                    free &= self.check[place + o : place + o + window] < 0
                if free.any():
                    place += int(free.argmax())
                    break
                place, window = place + window, min(2 * window, 1 << 16)
            self.base[node] = place
            for code, a, b in groups:
                self.check[place + code] = node
                todo.append((place + code, a, b, depth + 1))

        # Every cell that a step may look at exists; a leaf's steps end among the root's children, not its own.
        room = int(self.base.max()) + 258 - len(self.check)
        if room > 0:
            self.base, self.check, self.value = (np.append(x, np.full(room, f, np.int32)) for x, f in ((self.base, 0), (self.check, -1), (self.value, -1)))

    def lists(self) -> tuple[list[int], list[int], list[int]]:
        return self.base.tolist(), self.check.tolist(), self.value.tolist()


class PieceModel:
    """Encoder and decoder of one model file; what it unpickles to builds its lookup lists once a worker."""

    def __init__(self, data: bytes):
        self.pieces, self.prefix = read_model(data)
        plain = [(p, i) for i, (p, _, kind) in enumerate(self.pieces) if kind in (1, 4) and p]
        self.bytes = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(self.pieces) if kind == 6}
        if len(self.bytes) < 256:
            raise ValueError("the model has no byte pieces")
        self.trie = DoubleArray([(p.encode(), i) for p, i in plain])
        self.score = [s for _, s, _ in self.pieces]
        self.unknown = min((self.score[i] for p, i in plain if set(p) != {MARK}), default=0.0) - UNKNOWN
        held = {c for p, _ in plain for c in p}
        apart = "".join(re.escape(c) for c in "\n\t\r" if c not in held)
        self.split = not any(MARK in p.lstrip(MARK) for p, _ in plain)
        parts = f"{MARK}+[^{MARK}{apart}]*|[^{MARK}{apart}]+" + (f"|[{apart}]" if apart else "")
        self.parts = re.compile(parts if self.split else r"(?s).+")
        self._start()

    def _start(self):
        self.base, self.check, self.value = self.trie.lists()
        self.cache: dict[str, bytes] = {}
        # A byte below 128 is a character of its own; the others are gathered before they are decoded.
        self.byte_of = {i: b for b, i in self.bytes.items()}
        self.text = [p.replace(MARK, " ") if kind in (1, 4) else "" for p, _, kind in self.pieces]
        self.is_byte, self.gathered = np.zeros(len(self.pieces), bool), np.zeros(len(self.pieces), bool)
        for b, i in self.bytes.items():
            self.text[i] = chr(b) if b < 128 else None
            self.is_byte[i], self.gathered[i] = True, b >= 128

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("base", "check", "value", "cache", "text", "byte_of", "is_byte", "gathered")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._start()

    def best(self, part: str) -> tuple[int, ...]:
        """Ids of the best segmentation of one part (spaces already markers)."""
        data = part.encode("utf-8", "surrogatepass")
        base, check, value, score = self.base, self.check, self.value, self.score
        n = len(data)
        total: list[float | None] = [None] * (n + 1)
        back: list[tuple[int, int]] = [(0, 0)] * (n + 1)
        total[0] = 0.0
        for s in range(n):
            here = total[s]
            if here is None:
                continue
            lead = data[s]
            width = 1 if lead < 128 else 2 if lead < 224 else 3 if lead < 240 else 4
            node, at, single = 0, s, False
            while at < n:
                to = base[node] + data[at] + 1
                if check[to] != node:
                    break
                node = to
                at += 1
                piece = value[node]
                if piece >= 0:
                    single = single or at == s + width
                    sum_ = here + score[piece]
                    if total[at] is None or sum_ > total[at]:
                        total[at], back[at] = sum_, (s, piece)
            if not single:
                at, sum_ = s + width, here + self.unknown
                if total[at] is None or sum_ > total[at]:
                    total[at], back[at] = sum_, (s, -1)
        out: list[int] = []
        at = n
        while at:
            s, piece = back[at]
            if piece >= 0:
                out.append(piece)
            else:
                raw = data[s:at].decode("utf-8", "surrogatepass").replace(_LITERAL, MARK).encode()
                out += [self.bytes[b] for b in reversed(raw)]
            at = s
        return tuple(reversed(out))

    def encode(self, text: str | None) -> np.ndarray:
        """Ids of a text (int32)."""
        if not text:
            return np.zeros(0, np.int32)
        marked = text.replace(MARK, _LITERAL).replace(" ", MARK)
        parts = self.parts.findall(MARK + marked if self.prefix else marked)
        new = set(parts).difference(self.cache)
        if len(self.cache) + len(new) > CACHE:
            self.cache.clear()
            new = set(parts)
        for part in new:
            self.cache[part] = np.array(self.best(part), np.int32).tobytes()
        out = np.frombuffer(b"".join(map(self.cache.__getitem__, parts)), np.int32)
        for part in new:
            if len(part) > 64:
                del self.cache[part]
        return out

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids."""
        if not self.gathered[ids].any():
            joined = "".join(map(self.text.__getitem__, ids.tolist()))
        else:
            out, raw = [], bytearray()
            for i in ids.tolist():
                if self.gathered[i]:
                    raw.append(self.byte_of[i])
                    continue
                if raw:
                    out.append(raw.decode("utf-8", "replace"))
                    raw.clear()
                out.append(self.text[i])
            joined = "".join([*out, raw.decode("utf-8", "replace")])
        return joined[1:] if self.prefix and joined.startswith(" ") else joined


def load(path: str = MODEL) -> PieceModel:
    """The model in a file that the driver can open."""
    with open(path, "rb") as f:
        return PieceModel(f.read())


def encode(docs: DataFrame, model: PieceModel) -> DataFrame:
    """``doc_id, ids, n_pieces, n_byte_pieces, round_trip`` for each row of ``docs(doc_id, text)``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        m = shared.value

        def one(text):
            ids = m.encode(text)
            return ids, len(ids), int(m.is_byte[ids].sum()), m.decode(ids) == text

        return one

    encoded = by_row(make, "ids array<int>, n_pieces int, n_byte_pieces int, round_trip boolean")
    return docs.select("doc_id", encoded("text").alias("e")).select("doc_id", "e.*")


def decode(encoded: DataFrame, model: PieceModel) -> DataFrame:
    """``doc_id, text`` for each row of ``encoded(doc_id, ids)``; null ids are the empty text."""
    shared = encoded.sparkSession.sparkContext.broadcast(model)
    text = by_row(lambda: lambda x: shared.value.decode(np.asarray(x or [], np.int64)), "string")
    return encoded.select("doc_id", text("ids").alias("text"))
