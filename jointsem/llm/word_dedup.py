"""Removal of words covered by a window of words that starts at a second place, found by recompression.

Windows of `width` words are grouped by a symbol of the recompressed text that
is fixed inside them; a symbol found at several places reveals a repeat.  Rounds of
Spark then name the words, runs and pairs of the revealed places, so that a name
stands for one string.  Windows are equal if they hold the same symbol at the same
place and the same names beside it: the symbol's name verifies its own words.
Equal texts are recognised first: all their windows repeat.

Nulls: a null text has no words; null ids are allowed.  Two rows with equal
texts are two places, also if their ids are equal.  Of a column of docs that has the
name of a result, the result stays.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.llm import blobs
from jointsem.llm.recompression import ROUNDS, Definitions, Names, anchors, compress
from jointsem.llm.repeats import chosen, ragged_pack, same_bytes, with_spans
from jointsem.llm.store import stage
from jointsem.llm.text import Prefix, Words, gather, merged, mix, slices, space_table, starts_of_runs

WIDTH = 35
#: Numbers before the names of a piece.
HEAD = 3
#: Definitions that share a 64-bit name are told to every task: at most so many, found in so many repeats of a round.
MOST_SHARED, MOST_REPEATS = 1 << 20, 8
_HELD, _CHECKED = 8 << 20, 1 << 15
_NAMED = {"kind": np.uint8, "name": np.uint64, "size": np.int32, "content": np.uint8}
_MADE = ("n_words", "n_removed", "kept_sha256")


class _WordScan:
    def __init__(self, texts: list[bytes], width: int, rounds: int, names: Names, define: int = 0):
        words = Words(texts, space_table())
        codes = names.cut(words.hashes())
        self.width = width
        self.words = Definitions(0, codes, np.arange(len(codes)), words.starts, words.ends - words.starts, words.data)
        self.exact = names.resolve(self.words)
        self.symbols, self.made = compress(codes, self.exact, words.doc, words.first, names, rounds, define)
        self.h, self.start, self.count, self.symbol = anchors(codes, self.symbols, words.first, width)
        self.doc = words.doc[self.start]
        self.first = self.start - words.first[self.doc]

    def definitions(self, at: np.ndarray, level: int) -> list[Definitions]:
        """What the names of a level stand for that decide about the windows of these anchors: their words, or the parts of their symbols."""
        cover = np.zeros(len(self.exact) + 1, np.int64)
        if level:
            own = self.symbol[at][self.symbol[at] >= 0]
            start, stop = self.symbols.start[own], self.symbols.stop[own]
        else:
            start, stop = self.start[at], self.start[at] + self.count[at] + self.width - 1
        np.add.at(cover, start, 1)
        np.add.at(cover, stop, -1)
        inside = np.cumsum(cover) > 0
        found = self.made if level else [self.words]
        return [d.take(np.flatnonzero(inside[d.word])) for d in found]

    def pieces(self, at: np.ndarray, skip: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """A piece is its symbol's name, the number of the symbol's words, the place of the symbol, and the names of all other words."""
        some, start = self.symbol[at] >= 0, self.start[at] + skip
        symbol = np.where(some, self.symbol[at], 0)
        cut = np.where(some, self.symbols.stop[symbol] - self.symbols.start[symbol], 0)
        before = np.where(some, self.symbols.start[symbol] - start, 0)
        size = count + self.width - 1 - cut
        step = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
        place = np.repeat(start, size) + step + np.where(step >= np.repeat(before, size), np.repeat(cut, size), 0)
        whole = size + HEAD
        begin = np.cumsum(whole) - whole
        flat = np.zeros(int(whole.sum()), np.uint64)
        flat[begin], flat[begin + 1], flat[begin + 2] = np.where(some, self.symbols.exact[symbol], np.uint64(0)), cut.astype(np.uint64), before.astype(np.uint64)
        flat[np.repeat(begin + HEAD, size) + step] = self.exact[place]
        return mix(Prefix(flat).span(begin, begin + whole)), 8 * whole, flat.view(np.uint8)


class WordScheme:
    by_id = False
    piece_bytes = 0

    def __init__(self, width: int = WIDTH, rounds: int = ROUNDS, names: Names | None = None):
        self.width, self.rounds, self.names = width, rounds, names or Names()

    def scan(self, texts: list[bytes], define: int = 0) -> _WordScan:
        return _WordScan(texts, self.width, self.rounds, self.names, define)

    def named(self, rows: DataFrame, parts: int) -> tuple[WordScheme, DataFrame]:
        """The scheme with exact names for the words and symbols that decide about rows, and rows as a table.

        Level by level a Spark job brings all definitions of a name together;
        it is repeated while it finds definitions that share one.
        """
        rows, scheme = stage(rows, "revealed"), self
        for level in range(self.rounds + 1):
            for _ in range(MOST_REPEATS):
                shared = _shared_names(rows, scheme, level, parts).limit(MOST_SHARED + 1).collect()
                if len(shared) > MOST_SHARED:
                    raise RuntimeError(f"over {MOST_SHARED} definitions share a 64-bit name")
                if not shared:
                    break
                by: dict[tuple[int, int], list[bytes]] = {}
                for r in shared:
                    by.setdefault((r.kind, r.name % 2**64), []).append(bytes(r.definition))
                names = Names({k: {n: dict(d) for n, d in t.items()} for k, t in scheme.names.table.items()}, scheme.names.bits)
                for (kind, name), definitions in by.items():
                    names.add(kind, name, definitions)
                if names.table == scheme.names.table:
                    break
                scheme = WordScheme(self.width, self.rounds, names)
        return scheme, rows

    def classes(self, content: np.ndarray, offset: np.ndarray, count: np.ndarray) -> np.ndarray:
        """Windows are equal if the names of their symbols are, at the same place, and the names of all other words; sorting by a hash of these is checked name by name."""
        every = content.view(np.uint64)
        size = (HEAD + count + self.width - 1 - every[offset // 8 + 1].astype(np.int64)).astype(np.int64)
        flat, begin = gather(every, offset // 8, size), np.cumsum(size) - size
        owner = np.repeat(np.arange(len(count)), count)
        step = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
        symbol, cut = flat[begin][owner], flat[begin + 1][owner].astype(np.int64)
        before = np.where(cut > 0, flat[begin + 2][owner].astype(np.int64) - step, 0)
        start, wide = begin[owner] + HEAD + step, self.width - cut
        key = mix(Prefix(flat).span(start, start + wide) ^ mix(symbol + (before * (self.width + 1) + cut).astype(np.uint64)))
        order = np.argsort(key, kind="stable")
        same = key[order[1:]] == key[order[:-1]]
        for i in range(0, len(same), _CHECKED):
            a, b = order[i : i + _CHECKED + 1][:-1], order[i : i + _CHECKED + 1][1:]
            at = np.flatnonzero(same[i : i + _CHECKED])
            a, b = a[at], b[at]
            if not len(at):
                continue
            alike = (symbol[a] == symbol[b]) & (cut[a] == cut[b]) & (before[a] == before[b])
            if alike.all():
                equal = gather(flat, start[a], wide[a]) == gather(flat, start[b], wide[b])
                alike = np.logical_and.reduceat(equal, np.cumsum(wide[a]) - wide[a]) if len(equal) else alike
            if not alike.all():
                return self._compared(flat, symbol, cut, before, start, wide)
        out = np.zeros(len(order), np.int64)
        out[order] = np.cumsum(np.append(0, ~same))
        return out

    def _compared(self, flat: np.ndarray, symbol: np.ndarray, cut: np.ndarray, before: np.ndarray, start: np.ndarray, wide: np.ndarray) -> np.ndarray:
        """The classes without a hash, for windows that share one."""
        table: dict[tuple, int] = {}
        return np.array([table.setdefault((s, c, b, flat[i : i + w].tobytes()), len(table)) for s, c, b, i, w in zip(symbol.tolist(), cut.tolist(), before.tolist(), start.tolist(), wide.tolist(), strict=True)], np.int64)


def _distinct(found: list[Definitions]) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """Each name with its definition, and further definitions of it that differ from the first."""
    size = np.concatenate([d.size for d in found]).astype(np.int64)
    kind = np.repeat(np.array([d.kind for d in found], np.uint8), [len(d.name) for d in found])
    name = np.concatenate([d.name for d in found])
    content = np.concatenate([gather(d.flat, d.at, d.size.astype(np.int64)) for d in found])
    return _unshared(kind, name, size, content)


def _unshared(kind: np.ndarray, name: np.ndarray, size: np.ndarray, content: np.ndarray) -> tuple[dict[str, np.ndarray], np.ndarray]:
    start = np.cumsum(size) - size
    order = np.lexsort((name, kind))
    kind, name, size, start = kind[order], name[order], size[order], start[order]
    new = starts_of_runs(kind, name) if len(name) else np.zeros(0, bool)
    keep = new | ~same_bytes(content, start, size, np.flatnonzero(new)[np.cumsum(new) - 1]) if len(name) else new
    return {"kind": kind[keep], "name": name[keep], "size": size[keep].astype(np.int32)}, gather(content, start[keep], size[keep])


def _shared_names(rows: DataFrame, scheme: WordScheme, level: int, parts: int) -> DataFrame:
    """(kind, name, definition) of the names of a level that stand for several definitions."""

    def define(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[dict[str, np.ndarray], np.ndarray]] = []

        def flush() -> pa.RecordBatch:
            columns = {k: np.concatenate([c[k] for c, _ in held]) for k in held[0][0]}
            columns, content = _unshared(columns["kind"], columns["name"], columns["size"].astype(np.int64), np.concatenate([x for _, x in held]))
            return ragged_pack(blobs.part_of(columns["name"], parts), columns, "content", columns["size"].astype(np.int64), content, _NAMED)

        for batch, texts in slices(batches):
            s = scheme.scan(texts, level)
            at = chosen(s, batch)
            if len(at):
                held.append(_distinct(s.definitions(at, level)))
            if sum(len(x) for _, x in held) >= _HELD:
                yield flush()
                held = []
        if held:
            yield flush()

    def compare(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        columns, content = _unshared(x["kind"], x["name"], x["size"].astype(np.int64), x["content"])
        new = starts_of_runs(columns["kind"], columns["name"]) if len(columns["name"]) else np.zeros(0, bool)
        several = np.bincount(np.cumsum(new) - 1)[np.cumsum(new) - 1] > 1 if len(new) else new
        size = columns["size"].astype(np.int64)
        start = np.cumsum(size) - size
        out = {(int(columns["kind"][i]), int(columns["name"][i].view(np.int64)), content[start[i] : start[i] + size[i]].tobytes()) for i in np.flatnonzero(several).tolist()}
        if out:
            kind, name, definition = zip(*sorted(out), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(kind, pa.int32()), pa.array(name, pa.int64()), pa.array(definition, pa.binary())], names=["kind", "name", "definition"])

    defined = rows.select("firsts", "text").mapInArrow(define, blobs.schema(_NAMED))
    return blobs.reduce_parts(defined, parts, _NAMED, compare, "kind int, name long, definition binary")


def dedup_words(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, text_out: bool = False, bits: int = 64) -> DataFrame:
    """docs without the text column, with n_words, n_removed and kept_sha256; with text_out the text column holds the kept words; bits are those of the names' hashes."""
    columns = [c for c in docs.columns if c != text_col and c not in _MADE]
    safe = docs.select(F.col(text_col).alias("_body"), F.col(id_col).alias("_key"), *[F.col(c).alias(f"_{n}") for n, c in enumerate(columns)])
    found = with_spans(safe, WordScheme(width, names=Names(bits=bits)), "_key", "_body")
    rows = found.select(F.col("_text").alias("text"), F.coalesce(F.col("copies") == 1, F.lit(False)).alias("single"), F.col("_starts").alias("starts"), F.col("_stops").alias("stops"), *[f"_{n}" for n in range(len(columns))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            words = Words(texts, space_table())
            data = words.data.tobytes()
            single, starts, stops = (batch.column(k).to_pylist() for k in (1, 2, 3))
            out: list[tuple] = []
            for i in range(len(texts)):
                a, b = int(words.first[i]), int(words.first[i + 1])
                keep = np.ones(b - a, bool)
                if not single[i] and b - a >= width:
                    keep[:] = False
                else:
                    for x, y in zip(*merged(np.array(starts[i] or (), np.int64), np.array(stops[i] or (), np.int64)), strict=True):
                        keep[x:y] = False
                at = np.flatnonzero(keep) + a
                kept = b" ".join([data[x:y] for x, y in zip(words.starts[at].tolist(), words.ends[at].tolist(), strict=True)])
                out.append((b - a, b - a - len(at), hashlib.sha256(kept).hexdigest(), kept.decode() if text_out else ""))
            new = [pa.array([x[k] for x in out], kind) for k, kind in enumerate((pa.int64(), pa.int64(), pa.string(), pa.string()))]
            yield pa.RecordBatch.from_arrays([*batch.columns[4:], *new[: 4 if text_out else 3]], names=[*batch.schema.names[4:], "n_words", "n_removed", "kept_sha256", "text"][: len(batch.schema.names) - 1 + text_out])

    schema = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[4:]), "n_words long, n_removed long, kept_sha256 string", *(["text string"] if text_out else [])])
    done = rows.mapInArrow(run, schema).withColumnsRenamed({f"_{n}": c for n, c in enumerate(columns)})
    return done.withColumnRenamed("text", text_col) if text_out else done
