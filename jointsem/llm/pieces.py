"""SentencePiece BPE encoding and decoding in vectorised merge rounds.

The words of a slice (a run of word marks with what follows it) are reduced to
the distinct ones; their characters are one flat symbol array.  A round finds
the least pair rank of every word, leftmost first, merges all chosen pairs at
once and compacts the array; words without a pair drop out, until none is left.
Words of over LONG symbols use a heap instead, so that a text without spaces
does not need a round per character.  Results equal the library's for models
without a normalisation map, with byte fallback.

Words are grouped by 64-bit hashes and compared byte by byte; where two words
share a hash, the slice is encoded from its words themselves.

Nulls: a null text is empty and has no ids.  Repeated rows are returned as often as
they occur; other columns of docs are not returned and cannot clash.
"""

from __future__ import annotations

import hashlib
import heapq
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.llm.text import Prefix, gather, mix, slices, starts_of_runs

MARK = "▁".encode()
LONG = 256
CACHE = 1 << 18
_NORMAL, _BYTE = 1, 6
_NO_PAIR = np.int64(1) << 62


def _fields(data: bytes) -> Iterator[tuple[int, bytes | int]]:
    """Field numbers and values of a protocol-buffer message."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            b = data[at]
            value |= (b & 127) << shift
            at, shift = at + 1, shift + 7
            if b < 128:
                return value, at

    at = 0
    while at < len(data):
        key, at = varint(at)
        kind = key & 7
        if kind == 0:
            value, at = varint(at)
        elif kind == 2:
            n, at = varint(at)
            value, at = data[at : at + n], at + n
        else:
            n = 4 if kind == 5 else 8
            value, at = data[at : at + n], at + n
        yield key >> 3, value


class Model:
    """A BPE model's pieces, ranks and pair table, read from the bytes of its file."""

    def __init__(self, raw: bytes):
        pieces: list[tuple[str, float, int]] = []
        for number, value in _fields(raw):
            if number == 1:
                f = dict(_fields(value))
                pieces.append((f.get(1, b"").decode(), struct.unpack("<f", f[2])[0] if 2 in f else 0.0, f.get(3, _NORMAL)))
            elif number == 3:
                spec = dict(_fields(value))
                if spec.get(2) or not spec.get(3, 1) or spec.get(4, 1) or not spec.get(5, 1):
                    raise ValueError("only models with the identity normaliser, a leading mark and kept spaces are supported")
        self.n = len(pieces)
        ids = {p: i for i, (p, _, kind) in enumerate(pieces) if kind == _NORMAL}
        if any("▁" in p.lstrip("▁") for p in ids):
            raise ValueError("pieces across words are not supported")
        score = np.array([s for _, s, _ in pieces])
        order = np.unique(-score, return_inverse=True)[1].ravel()
        keys, merged = [], []
        for p, i in ids.items():
            for k in range(1, len(p)):
                a, b = ids.get(p[:k]), ids.get(p[k:])
                if a is not None and b is not None:
                    keys.append(a * self.n + b)
                    merged.append(i)
        at = np.argsort(np.array(keys, np.int64))
        self.pair = np.array(keys, np.int64)[at]
        self.merged = np.array(merged, np.int64)[at]
        self.rank = order[self.merged].astype(np.int64)
        single = sorted((int.from_bytes(p.encode(), "big"), i) for p, i in ids.items() if len(p) == 1)
        self.chars, self.char_id = (np.array(x, np.int64) for x in zip(*single, strict=True))
        self.byte_id = np.zeros(256, np.int64)
        spelled = [b" \xe2\x81\x87 " if kind == 2 else b"" for _, _, kind in pieces]
        for i, (p, _, kind) in enumerate(pieces):
            if kind == _BYTE:
                self.byte_id[int(p[1:-1], 16)] = i
                spelled[i] = bytes([int(p[1:-1], 16)])
            elif kind == _NORMAL:
                spelled[i] = p.replace("▁", " ").encode()
        self.size = np.array([len(s) for s in spelled], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.spelled = np.frombuffer(b"".join(spelled), np.uint8)

    def look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and merged id of symbol pairs; a symbol below zero joins nothing."""
        key = np.where((left >= 0) & (right >= 0), left * self.n + right, -1)
        at = np.minimum(np.searchsorted(self.pair, key), len(self.pair) - 1)
        hit = self.pair[at] == key
        return np.where(hit, self.rank[at], _NO_PAIR >> 32), np.where(hit, self.merged[at], -1)

    def symbols(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First byte of every character of valid UTF-8, and its piece, or -1."""
        at = np.flatnonzero(data & 0xC0 != 0x80)
        size = np.diff(np.append(at, len(data)))
        code = np.zeros(len(at), np.int64)
        for k in range(int(size.max(initial=0))):
            more = size > k
            code[more] = (code[more] << 8) | data[at[more] + k]
        i = np.minimum(np.searchsorted(self.chars, code), len(self.chars) - 1)
        return at, np.where(self.chars[i] == code, self.char_id[i], -1)

    def encode_words(self, data: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words that lie one after another in data from start[0] = 0, and the number of ids of each."""
        at, symbol = self.symbols(data)
        word = np.searchsorted(start, at, "right") - 1
        count = np.bincount(word, minlength=len(start))
        for w in np.flatnonzero(count > LONG).tolist():
            own = slice(int(np.searchsorted(word, w)), int(np.searchsorted(word, w, "right")))
            symbol[own], at[own] = self._heap(symbol[own], at[own])
        gone = at < 0
        symbol, at, word = symbol[~gone], at[~gone], word[~gone]
        live = np.flatnonzero(count[word] <= LONG)
        dead = np.zeros(len(symbol), bool)
        s, w, origin = symbol[live], word[live], live
        rank, into = self._ranks(s, w)
        while len(s):
            head = np.flatnonzero(starts_of_runs(w))
            best = np.minimum.reduceat((rank << 32) | np.arange(len(rank)), head)
            good = best < _NO_PAIR
            pos = best[good] & 0xFFFFFFFF
            symbol[origin[pos]] = into[pos]
            s[pos] = into[pos]
            dead[origin[pos + 1]] = True
            keep = np.repeat(good, np.diff(np.append(head, len(s))))
            keep[pos + 1] = False
            moved = np.cumsum(keep) - 1
            touched = moved[pos]
            s, w, origin, rank, into = s[keep], w[keep], origin[keep], rank[keep], into[keep]
            redo = np.unique(np.concatenate([touched, np.maximum(touched - 1, 0)]))
            if len(redo):
                self._ranks(s, w, redo, rank, into)
        keep = ~dead
        return self._with_bytes(symbol[keep], at[keep], word[keep], data, len(start))

    def _ranks(self, s: np.ndarray, w: np.ndarray, at: np.ndarray | None = None, rank: np.ndarray | None = None, into: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Rank of each symbol with the next of its word; only at `at` if given."""
        if rank is None:
            at, rank, into = np.arange(len(s)), np.full(len(s), _NO_PAIR >> 32), np.full(len(s), -1, np.int64)
        nxt = np.minimum(at + 1, len(s) - 1)
        r, m = self.look_up(s[at], s[nxt])
        inside = (nxt > at) & (w[at] == w[nxt])
        rank[at], into[at] = np.where(inside, r, _NO_PAIR >> 32), m
        return rank, into

    def _heap(self, symbol: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One long word by a heap of pairs; symbols merged away get the offset -1."""
        s, n = symbol.tolist(), len(symbol)
        nxt, prev = list(range(1, n + 1)), list(range(-1, n - 1))
        rank, into = (x.tolist() for x in self.look_up(symbol[:-1], symbol[1:]))
        none = int(_NO_PAIR >> 32)
        heap = [(rank[i], i, s[i], s[i + 1], into[i]) for i in range(n - 1) if rank[i] < none]
        heapq.heapify(heap)
        known: dict[tuple[int, int], tuple[int, int]] = {}

        def push(a: int, b: int) -> None:
            pair = s[a], s[b]
            if pair not in known:
                r, m = self.look_up(np.array([pair[0]]), np.array([pair[1]]))
                known[pair] = int(r[0]), int(m[0])
            r, m = known[pair]
            if r < none:
                heapq.heappush(heap, (r, a, *pair, m))

        gone = [False] * n
        while heap:
            _, a, left, right, m = heapq.heappop(heap)
            b = nxt[a]
            if gone[a] or b >= n or s[a] != left or s[b] != right:
                continue
            s[a], gone[b], nxt[a] = m, True, nxt[b]
            if nxt[a] < n:
                prev[nxt[a]] = a
                push(a, nxt[a])
            if prev[a] >= 0:
                push(prev[a], a)
        return np.array(s, np.int64), np.where(gone, -1, at)

    def _with_bytes(self, symbol: np.ndarray, at: np.ndarray, word: np.ndarray, data: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
        """Symbols without a piece replaced by the pieces of their bytes."""
        size = np.ones(len(symbol), np.int64)
        odd = symbol < 0
        first = data[at[odd]]
        size[odd] = 1 + (first >= 0xC0) + (first >= 0xE0) + (first >= 0xF0)
        out = np.repeat(symbol, size)
        place = np.repeat(at - (np.cumsum(size) - size), size) + np.arange(len(out))
        fill = np.repeat(odd, size)
        out[fill] = self.byte_id[data[place[fill]]]
        return out, np.bincount(np.repeat(word, size), minlength=words)

    def decode(self, ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """UTF-8 of several id lists, one after another, with byte offsets; first[i] is where list i starts, first[-1] the end."""
        size = self.size[ids].copy()
        start = self.start[ids]
        some = first[:-1][np.diff(first) > 0]
        lead = some[(size[some] > 0)]
        lead = lead[self.spelled[start[lead]] == 0x20]
        start[lead] += 1
        size[lead] -= 1
        return gather(self.spelled, start, size), np.append(0, np.cumsum(size))[first]


def _word_keys(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return mix(Prefix.of_bytes(data).span(start, end) + (end - start).astype(np.uint64))


def _alike(a: np.ndarray, a_start: np.ndarray, a_size: np.ndarray, b: np.ndarray, b_start: np.ndarray, b_size: np.ndarray) -> bool:
    """Whether each span of a has the bytes of its span of b."""
    return np.array_equal(a_size, b_size) and np.array_equal(gather(a, a_start, a_size), gather(b, b_start, b_size))


class Encoder:
    """Encodes slices of texts, keeping the ids of the words it met; the memory of words is bounded."""

    def __init__(self, model: Model):
        self.model = model
        self._clear()

    def _clear(self) -> None:
        self.keys = np.zeros(0, np.uint64)
        self.start = self.count = np.zeros(0, np.int64)
        self.ids = np.zeros(0, np.int64)
        self.text, self.at, self.size = np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Joined ids of the texts, and where each text's ids start (and the last end)."""
        marked = [MARK + t.replace(b" ", MARK) if t else b"" for t in texts]
        data = np.frombuffer(b"".join(marked), np.uint8)
        doc = np.concatenate([[0], np.cumsum([len(m) for m in marked])]).astype(np.int64)
        if not len(data):
            return np.zeros(0, np.int64), np.zeros(len(texts) + 1, np.int64)
        mark = np.zeros(len(data) + 3, bool)
        mark[3 : len(data) + 1] = (data[:-2] == 0xE2) & (data[1:-1] == 0x96) & (data[2:] == 0x81)
        new = mark[3:] & ~mark[:-3]
        new[doc[:-1][np.diff(doc) > 0]] = True
        start = np.flatnonzero(new)
        end = np.append(start[1:], len(data))
        key = _word_keys(data, start, end)
        unique, where, number = np.unique(key, return_index=True, return_inverse=True)
        if len(self.keys) + len(unique) > CACHE:
            self._clear()
        slot = np.searchsorted(self.keys, unique)
        known = np.zeros(len(unique), bool)
        inside = slot < len(self.keys)
        known[inside] = self.keys[slot[inside]] == unique[inside]
        size, number = end - start, number.ravel()
        held = slot[known]
        if not (_alike(data, start, size, data, start[where][number], size[where][number]) and _alike(data, start[where[known]], size[where[known]], self.text, self.at[held], self.size[held])):
            self._clear()
            spelled: dict[bytes, int] = {}
            whole = data.tobytes()
            number = np.array([spelled.setdefault(whole[a:b], len(spelled)) for a, b in zip(start.tolist(), end.tolist(), strict=True)])
            size = np.array([len(w) for w in spelled])
            flat, count = self.model.encode_words(np.frombuffer(b"".join(spelled), np.uint8), np.cumsum(size) - size)
            return gather(flat, (np.cumsum(count) - count)[number], count[number]), np.append(0, np.cumsum(count[number]))[np.searchsorted(start, doc)]
        fresh = where[~known]
        if len(fresh):
            size = size[fresh]
            text = gather(data, start[fresh], size)
            ids, count = self.model.encode_words(text, np.cumsum(size) - size)
            keys = np.concatenate([self.keys, unique[~known]])
            order = np.argsort(keys)
            self.start = np.concatenate([self.start, len(self.ids) + np.cumsum(count) - count])[order]
            self.count = np.concatenate([self.count, count])[order]
            self.ids = np.concatenate([self.ids, ids])
            self.at = np.concatenate([self.at, len(self.text) + np.cumsum(size) - size])[order]
            self.size = np.concatenate([self.size, size])[order]
            self.text = np.concatenate([self.text, text])
            self.keys = keys[order]
            slot = np.searchsorted(self.keys, unique)
        at = slot[number]
        ids = gather(self.ids, self.start[at], self.count[at])
        return ids, np.append(0, np.cumsum(self.count[at]))[np.searchsorted(start, doc)]


_DIGITS = {"start": np.zeros(0, np.int64), "size": np.zeros(0, np.int64), "flat": np.zeros(0, np.uint8)}


def _decimal(n: int) -> dict[str, np.ndarray]:
    """Decimal spelling of 0..n-1, each with a comma."""
    if len(_DIGITS["size"]) < n:
        spelled = [b"%d," % i for i in range(n)]
        size = np.array([len(s) for s in spelled], np.int64)
        _DIGITS.update(size=size, start=np.cumsum(size) - size, flat=np.frombuffer(b"".join(spelled), np.uint8))
    return _DIGITS


def round_trip(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", ids_out: bool = False) -> DataFrame:
    """id, n_tokens, ids_sha256 (decimal ids joined by commas) and decoded_sha256; with ids_out also ids and decoded.

    The driver reads the model file; tasks get its bytes.
    """
    with open(model_path, "rb") as f:
        raw = f.read()
    shared = docs.sparkSession.sparkContext.broadcast(raw)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(Model(shared.value))
        digits = _decimal(encoder.model.n)
        for batch, texts in slices(batches):
            ids, first = encoder.encode(texts)
            decoded, cut = encoder.model.decode(ids, first)
            size = digits["size"][ids]
            joined = gather(digits["flat"], digits["start"][ids], size).tobytes()
            ends = np.append(0, np.cumsum(size))[first].tolist()
            plain, cut = decoded.tobytes(), cut.tolist()
            n = len(texts)
            columns = [
                batch.column(0),
                pa.array(np.diff(first)),
                pa.array([hashlib.sha256(joined[ends[i] : max(ends[i], ends[i + 1] - 1)]).hexdigest() for i in range(n)]),
                pa.array([hashlib.sha256(plain[cut[i] : cut[i + 1]]).hexdigest() for i in range(n)]),
            ]
            if ids_out:
                columns += [pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(ids.astype(np.int32))), pa.array([plain[cut[i] : cut[i + 1]].decode(errors="replace") for i in range(n)])]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: len(columns)])

    schema = "id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if ids_out else "")
    return rows.mapInArrow(run, schema).withColumnRenamed("id", id_col)
