"""Repeated windows of texts: the distributed part shared by the substring operators.

Windows of a fixed width are grouped by anchors: a scheme's scan() gives, for
each text, runs of consecutive windows with one content-defined hash, so equal
windows anywhere have equal hashes.  Then

1. anchors are counted over all texts, and those of several places (or texts)
   are returned to their texts;
2. only their windows are compared.  A run of windows (a piece) is sent with
   its content to the task of its anchor; equal pieces collapse to one, and
   windows of different pieces are compared in full.

Hot anchors do not gather in one task.  A map task sends one row per anchor and
one per distinct piece, however many copies it holds, and answers the others
itself.  The windows of an anchor with more than `hot` rows are dealt one by
one by their own content.  The table of such anchors is bounded: at most
_HOT_SHARE times the mean number of anchors of a text.  The number of parts of a
shuffle follows the bytes of the texts, so what a task holds does not grow with them.

The more texts there are, the more of their anchors occur twice by chance.  Where
the pieces would take more than the texts do, they are compared in passes, each
over the anchors of some hashes, so that a pass shuffles no more than the texts;
the texts with such anchors are then kept as a table, and what a pass shuffled is
deleted before the next one.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.llm import blobs
from jointsem.llm.store import stage, tidy
from jointsem.llm.text import gather, merged, mix, slices, starts_of_runs

#: Bytes of distinct texts for each part of a shuffle; a part takes a few times as much.
PART_BYTES = 16 << 20
CHUNK = 1 << 18
CHUNK_BYTES = 8 << 20
BLOCK = 1 << 17
_HOT_LEAST = 4096
_HOT_SHARE = 20_000
#: Pieces of so many bytes go in one pass, however small the texts are.
PASS_LEAST = 64 << 20
_MANY = -1
_COUNTED = {"h": np.uint64, "th": np.int64, "first": np.int32, "n": np.int32, "known": np.int64, "known_first": np.int32}
_FOUND = {"th": np.int64, "first": np.int32, "hot": np.uint64}
_SPANS = {"id": np.int64, "th": np.int64, "start": np.int32, "stop": np.int32}
_PIECES = {"h": np.uint64, "ph": np.uint64, "id": np.int64, "th": np.int64, "first": np.int32, "count": np.int32, "many": np.uint8, "size": np.int32, "content": np.uint8, "d_id": np.int64, "d_th": np.int64, "d_first": np.int32, "d_count": np.int32}


class Scan(Protocol):
    """Anchors of a slice of texts; first is a window's place in its text."""

    h: np.ndarray
    doc: np.ndarray
    first: np.ndarray
    count: np.ndarray

    def pieces(self, at: np.ndarray, skip: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hash, size in bytes, and joined content of pieces: count windows from the skip-th of anchor at."""


class Scheme(Protocol):
    width: int
    by_id: bool  #: True: a window is repeated if a smaller id holds it; False: if it starts at a second place
    piece_bytes: int  #: what a piece takes in a shuffle, about; 0: all go in one pass

    def scan(self, texts: list[bytes]) -> Scan: ...

    def named(self, rows: DataFrame, parts: int) -> tuple[Scheme, DataFrame]:
        """The scheme and rows (id, th, firsts, text) as the comparison is to use them."""

    def classes(self, content: np.ndarray, offset: np.ndarray, count: np.ndarray) -> np.ndarray:
        """A class for every window of pieces, piece after piece; equal windows share one."""


@dataclass
class Work:
    scheme: Scheme
    parts: int
    turn: int = 0
    passes: int = 1

    @property
    def pass_parts(self) -> int:
        return -(-self.parts // self.passes)

    def part(self, h: np.ndarray) -> np.ndarray:
        """The part of an anchor inside its pass."""
        return blobs.part_of(h, self.parts) // self.passes

    def mine(self, h: np.ndarray) -> np.ndarray:
        return blobs.part_of(h, self.parts) % self.passes == self.turn


def ragged_pack(part: np.ndarray, columns: dict[str, np.ndarray], ragged: str, sizes: np.ndarray, flat: np.ndarray, every: dict[str, type]) -> pa.RecordBatch:
    """blobs.pack with one column of variable size; columns of `every` that are not given are empty."""
    order = np.argsort(part, kind="stable")
    start = np.cumsum(sizes) - sizes
    flat = gather(flat, start[order], sizes[order])
    ids, first = np.unique(part[order], return_index=True)
    bounds = np.append(first, len(part))
    cut = np.append(0, np.cumsum(sizes[order]))[bounds]
    data: list[pa.Array] = [pa.array(ids.astype(np.int32))]
    for name in every:
        if name == ragged:
            values, at = np.ascontiguousarray(flat), cut
        elif name in columns:
            values, at = np.ascontiguousarray(columns[name][order]), bounds
        else:
            values, at = np.zeros(0, np.uint8), np.zeros(len(bounds), np.int64)
        data.append(pa.array([values[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)], pa.binary()))
    return pa.RecordBatch.from_arrays(data, names=["part", *every])


def _count_map(work: Work):
    scheme, parts = work.scheme, work.parts

    def flush(h: np.ndarray, th: np.ndarray, first: np.ndarray) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((first, th, h))
        h, th, first = h[order], th[order], first[order]
        keep = starts_of_runs(h, th, first)
        h, th, first = h[keep], th[keep], first[keep]
        at = np.flatnonzero(starts_of_runs(h))
        end = np.append(at[1:], len(h))
        many = th[at] != th[end - 1] if scheme.by_id else end - at > 1
        inner = np.repeat(many, end - at)
        single = ~inner
        n = np.ones(len(h), np.int32)
        yield ragged_pack(blobs.part_of(h[single], parts), {"h": h[single], "th": th[single], "first": first[single].astype(np.int32), "n": n[single]}, "", np.zeros(single.sum(), np.int64), np.zeros(0, np.uint8), _COUNTED)
        if many.any():
            m = at[many]
            yield ragged_pack(blobs.part_of(h[m], parts), {"h": h[m], "th": th[m], "first": np.full(len(m), _MANY, np.int32), "n": (end - at)[many].astype(np.int32)}, "", np.zeros(len(m), np.int64), np.zeros(0, np.uint8), _COUNTED)
            part = _part_of_text(th[inner], parts)
            yield ragged_pack(part, {"known": th[inner], "known_first": first[inner].astype(np.int32)}, "", np.zeros(len(part), np.int64), np.zeros(0, np.uint8), _COUNTED)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0
        for batch, texts in slices(batches):
            s = scheme.scan(texts)
            if len(s.h):
                held.append((s.h, batch.column(0).to_numpy()[s.doc], s.first))
                size += len(s.h)
            if size >= CHUNK:
                yield from flush(*(np.concatenate(x) for x in zip(*held, strict=True)))
                held, size = [], 0
        if held:
            yield from flush(*(np.concatenate(x) for x in zip(*held, strict=True)))

    return run


def _lists(keys: tuple[np.ndarray, ...], names: list[str], values: list[np.ndarray], value_names: list[str]) -> pa.RecordBatch:
    """One row per run of equal keys, with lists of the values."""
    at = np.flatnonzero(starts_of_runs(*keys)) if len(keys[0]) else np.zeros(0, np.int64)
    offsets = pa.array(np.append(at, len(keys[0])).astype(np.int32))
    lists = [pa.ListArray.from_arrays(offsets, pa.array(v.astype(np.int32))) for v in values]
    return pa.RecordBatch.from_arrays([*(pa.array(k[at]) for k in keys), *lists], names=[*names, *value_names])


def candidates(texts: DataFrame, scheme: Scheme, n_texts: int, parts: int) -> DataFrame:
    """(th, text) -> blobs of (th, first): anchors of several places, dealt by text; rows of part -1 hold hot anchors in `hot`."""
    hot_rows = max(_HOT_LEAST, n_texts // _HOT_SHARE)

    def reduce(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((x["first"], x["th"], x["h"]))
        h, th, first, n = (x[c][order] for c in ("h", "th", "first", "n"))
        keep = starts_of_runs(h, th, first) | (first == _MANY)
        h, th, first, n = h[keep], th[keep], first[keep], n[keep]
        out_th, out_first, hot = [x["known"]], [x["known_first"]], np.zeros(0, np.uint64)
        if len(h):
            at = np.flatnonzero(starts_of_runs(h))
            end = np.append(at[1:], len(h))
            again = np.logical_or.reduceat(first == _MANY, at) | (th[at] != th[end - 1] if scheme.by_id else end - at > 1)
            chosen = np.repeat(again, end - at) & (first != _MANY)
            out_th.append(th[chosen])
            out_first.append(first[chosen])
            hot = h[at][np.add.reduceat(n.astype(np.int64), at) > hot_rows]
        th, first = np.concatenate(out_th), np.concatenate(out_first)
        if len(th):
            yield _filled(blobs.pack(_part_of_text(th, parts), {"th": th, "first": first}), _FOUND)
        if len(hot):
            yield _filled(blobs.pack(np.full(len(hot), -1), {"hot": hot}), _FOUND)

    mapped = texts.select("th", "text").mapInArrow(_count_map(Work(scheme, parts)), blobs.schema(_COUNTED))
    return blobs.reduce_parts(mapped, parts, _COUNTED, reduce, blobs.schema(_FOUND))


def by_text(found: DataFrame, parts: int) -> DataFrame:
    """Blobs of candidates() -> (th, firsts), one row per text."""

    def gather_text(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((x["first"], x["th"]))
        th, first = x["th"][order], x["first"][order]
        keep = starts_of_runs(th, first)
        yield _lists((th[keep],), ["th"], [first[keep]], ["firsts"])

    columns = {c: _FOUND[c] for c in ("th", "first")}
    return blobs.reduce_parts(found.where("part >= 0"), parts, columns, gather_text, "th long, firsts array<int>")


def _part_of_text(th: np.ndarray, parts: int) -> np.ndarray:
    return blobs.part_of(mix(th.view(np.uint64)), parts)


def _filled(batch: pa.RecordBatch, columns: dict[str, type]) -> pa.RecordBatch:
    """batch with empty blobs for the columns it lacks."""
    empty = pa.array([b""] * batch.num_rows, pa.binary())
    return pa.RecordBatch.from_arrays([batch.column(0), *(batch.column(batch.schema.get_field_index(c)) if c in batch.schema.names else empty for c in columns)], names=["part", *columns])


def _union(id_: np.ndarray, th: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, ...]:
    """Merged spans of each (id, th), in order."""
    order = np.lexsort((start, th, id_))
    id_, th, start, stop = id_[order], th[order], start[order].astype(np.int64), stop[order].astype(np.int64)
    new = starts_of_runs(id_, th) if len(id_) else np.zeros(0, bool)
    number = np.cumsum(new) - 1
    at = np.flatnonzero(new)
    a, b = merged(start + (number << 32), stop + (number << 32))
    own = at[a >> 32]
    return id_[own], th[own], (a & 0xFFFFFFFF).astype(np.int32), (b & 0xFFFFFFFF).astype(np.int32)


def chosen(s: Scan, batch: pa.RecordBatch) -> np.ndarray:
    """The anchors whose first windows `firsts` names."""
    firsts = batch.column(batch.schema.get_field_index("firsts"))
    wanted = (np.repeat(np.arange(len(firsts)), [len(x) for x in firsts]) << 32) | np.asarray(firsts.flatten()).astype(np.int64)
    return np.flatnonzero(np.isin((s.doc.astype(np.int64) << 32) | s.first, wanted)) if len(s.h) else np.zeros(0, np.int64)


def _piece_map(work: Work, hot: np.ndarray):
    scheme = work.scheme

    def flush(c: dict[str, np.ndarray], content: np.ndarray) -> Iterator[pa.RecordBatch]:
        start = np.cumsum(c["size"]) - c["size"]
        order = np.lexsort((c["first"], c["th"], c["id"], c["ph"], c["count"], c["h"]))
        c = {k: v[order] for k, v in c.items()}
        start = start[order]
        new = starts_of_runs(c["h"], c["count"], c["ph"])
        at = np.flatnonzero(new)
        end = np.append(at[1:], len(new))
        run = np.cumsum(new) - 1
        same = same_bytes(content, start, c["size"], at[run])
        if scheme.by_id:
            answered = same & (c["id"] > c["id"][at[run]])
            many = np.zeros(len(new), np.uint8)
        else:
            twice = np.repeat(end - at > 1, end - at) & np.repeat(np.logical_and.reduceat(same, at), end - at)
            answered, many = twice, twice.astype(np.uint8)
        send = ~answered | (many.astype(bool) & new)
        sizes = c["size"][send].astype(np.int64)
        sent = {k: v[send] for k, v in (c | {"many": many}).items()}
        yield ragged_pack(work.part(sent["h"]), sent, "content", sizes, gather(content, start[send], sizes), _PIECES)
        if answered.any():
            done = {f"d_{k}": c[k][answered] for k in ("id", "th", "first", "count")}
            part = _part_of_text(done["d_th"], work.pass_parts)
            yield ragged_pack(part, done, "content", np.zeros(len(part), np.int64), np.zeros(0, np.uint8), _PIECES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict[str, np.ndarray]] = []
        contents: list[np.ndarray] = []
        size = 0
        for batch, texts in slices(batches):
            s = scheme.scan(texts)
            at = chosen(s, batch)
            one_by_one = np.isin(s.h[at], hot)
            now = one_by_one | work.mine(s.h[at])
            at, one_by_one = at[now], one_by_one[now]
            if not len(at):
                continue
            skip, count, h = np.zeros(len(at), np.int64), s.count[at], s.h[at]
            if one_by_one.any():
                wide = np.where(one_by_one, count, 1)
                step = np.arange(wide.sum()) - np.repeat(np.cumsum(wide) - wide, wide)
                at, one_by_one = np.repeat(at, wide), np.repeat(one_by_one, wide)
                skip, count, h = step, np.where(one_by_one, 1, s.count[at]), s.h[at]
            ph, sizes, content = s.pieces(at, skip, count)
            h = np.where(one_by_one, mix(ph + np.uint64(7)), h)
            now = work.mine(h)
            if not now.all():
                content = gather(content, (np.cumsum(sizes) - sizes)[now], sizes[now])
                at, skip, count, h, ph, sizes = (x[now] for x in (at, skip, count, h, ph, sizes))
            doc = s.doc[at]
            held.append({"h": h, "ph": ph, "id": batch.column(0).to_numpy()[doc], "th": batch.column(1).to_numpy()[doc], "first": (s.first[at] + skip).astype(np.int32), "count": count.astype(np.int32), "size": sizes.astype(np.int32)})
            contents.append(content)
            size += len(content)
            if size >= CHUNK_BYTES:
                yield from flush({k: np.concatenate([x[k] for x in held]) for k in held[0]}, np.concatenate(contents))
                held, contents, size = [], [], 0
        if held:
            yield from flush({k: np.concatenate([x[k] for x in held]) for k in held[0]}, np.concatenate(contents))

    return run


def same_bytes(content: np.ndarray, start: np.ndarray, size: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Whether each piece has the bytes of piece other[i]."""
    size = size.astype(np.int64)
    same = size == size[other]
    at = np.flatnonzero(same & (other != np.arange(len(other))))
    if len(at):
        equal = gather(content, start[at], size[at]) == gather(content, start[other[at]], size[at])
        same[at] = np.logical_and.reduceat(equal, np.cumsum(size[at]) - size[at])
    return same


def _blocks(heads: np.ndarray, anchor: np.ndarray, count: np.ndarray) -> Iterator[np.ndarray]:
    """Heads in blocks of about BLOCK windows, all of one anchor in one block."""
    i = 0
    total = np.cumsum(count[heads].astype(np.int64))
    while i < len(heads):
        j = int(np.searchsorted(total, (total[i - 1] if i else 0) + BLOCK, "right"))
        j = int(np.searchsorted(anchor, anchor[max(i, min(j, len(heads)) - 1)], "right"))
        yield heads[i:j]
        i = j


def _joined(row: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last of runs of consecutive numbers s of one row, and where they begin."""
    if not len(row):
        return s, s, row
    new = np.ones(len(row), bool)
    new[1:] = (row[1:] != row[:-1]) | (s[1:] != s[:-1] + 1)
    edge = np.flatnonzero(new)
    return s[edge], s[np.append(edge[1:], len(s)) - 1], edge


def repeated_spans(texts: DataFrame, scheme: Scheme, hot: np.ndarray, parts: int, passes: int = 1) -> tuple[DataFrame, list[DataFrame]]:
    """(id, th, firsts, text) -> (id, th, starts, stops): the spans covered by repeated windows, one row per text that has any; and the stage tables that this reads."""
    reach = scheme.width - 1

    def reduce(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        outs = [(x["d_id"], x["d_th"], x["d_first"], x["d_first"] + x["d_count"] + reach)]
        if len(x["h"]):
            size = x["size"].astype(np.int64)
            start = np.cumsum(size) - size
            order = np.lexsort((x["first"], x["th"], x["id"], x["ph"], x["count"], x["h"]))
            h, ph, id_, th, first, count, many = (x[k][order] for k in ("h", "ph", "id", "th", "first", "count", "many"))
            start, size = start[order], size[order]
            new = starts_of_runs(h, count, ph)
            new |= ~same_bytes(x["content"], start, size, np.flatnonzero(new)[np.cumsum(new) - 1])
            at = np.flatnonzero(new)
            end = np.append(at[1:], len(h))
            run = np.cumsum(new) - 1
            if scheme.by_id:
                whole = id_ > id_[at[run]]
            else:
                whole = np.repeat((np.add.reduceat(many.astype(np.int64), at) > 0) | (end - at > 1), end - at)
            outs.append((id_[whole], th[whole], first[whole], first[whole] + count[whole] + reach))
            fresh = starts_of_runs(h[at])
            several = np.add.reduceat(np.ones(len(at), np.int64), np.flatnonzero(fresh))
            lone = np.repeat(several > 1, several)
            number = np.full(len(at), -1)
            for heads in _blocks(at[lone], np.cumsum(fresh)[lone], count):
                n = count[heads].astype(np.int64)
                cls = scheme.classes(x["content"], start[heads], n)
                owner = np.repeat(np.arange(len(heads)), n)
                if scheme.by_id:
                    least = np.full(cls.max() + 1, np.iinfo(np.int64).max)
                    np.minimum.at(least, cls, id_[heads][owner])
                    hit = least[cls] < id_[heads][owner]
                else:
                    hit = np.bincount(cls)[cls] > 1
                window = np.flatnonzero(hit)
                offset = window - (np.cumsum(n) - n)[owner[window]]
                number[run[heads]] = np.arange(len(heads))
                lo, hi = run[heads[0]], run[heads[-1]] + 1
                rows = np.arange(at[lo], end[hi - 1])
                rows = rows[~whole[rows] & (number[run[rows]] >= 0)]
                each = np.bincount(owner[window], minlength=len(heads))
                begin = np.cumsum(each) - each
                k = number[run[rows]]
                row = np.repeat(rows, each[k])
                pick = np.repeat(begin[k] - (np.cumsum(each[k]) - each[k]), each[k]) + np.arange(len(row))
                s = first[row] + offset[pick]
                a, b, edge = _joined(row, s)
                outs.append((id_[row[edge]], th[row[edge]], a, b + reach + 1))
        made = dict(zip(_SPANS, _union(*(np.concatenate(c) for c in zip(*outs, strict=True))), strict=True))
        if len(made["th"]):
            yield blobs.pack(_part_of_text(made["th"], parts), made)

    def gather_spans(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        id_, th, a, b = _union(x["id"], x["th"], x["start"], x["stop"])
        yield _lists((id_, th), ["id", "th"], [a, b], ["starts", "stops"])

    def compared(work: Work) -> DataFrame:
        mapped = texts.select("id", "th", "firsts", "text").mapInArrow(_piece_map(work, hot), blobs.schema(_PIECES))
        return blobs.reduce_parts(mapped, work.pass_parts, _PIECES, reduce, blobs.schema(_SPANS))

    kept = [stage(compared(Work(scheme, parts, turn, passes)), "pass") for turn in range(passes)] if passes > 1 else []
    dealt = functools.reduce(DataFrame.unionAll, kept) if kept else compared(Work(scheme, parts))
    return blobs.reduce_parts(dealt, parts, _SPANS, gather_spans, "id long, th long, starts array<int>, stops array<int>"), kept


def passes_for(n_bytes: int, n_anchors: int, piece_bytes: int) -> int:
    """Passes of which each shuffles pieces of about as many bytes as the texts, or of PASS_LEAST bytes."""
    return max(1, -(-n_anchors * piece_bytes // max(n_bytes, PASS_LEAST)))


def text_keys(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs with _id (a null id is the largest), _text (a null text is empty) and two hashes of it, _th and _t2."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.withColumns({"_id": F.coalesce(F.col(id_col).cast("long"), F.lit(2**63 - 1)), "_text": text, "_th": F.xxhash64(text), "_t2": F.xxhash64(F.lit(1), text)})


def with_spans(docs: DataFrame, scheme: Scheme, id_col: str, text_col: str) -> DataFrame:
    """docs with _text, _copies (rows with that text), _least (their least id), _id, and for the text's first row _starts and _stops.

    The spans are those covered by repeated windows of different texts (or, for
    schemes by place, also of the same text); equal texts are left to the caller.
    """
    keyed = text_keys(docs, id_col, text_col)
    size = F.first(F.octet_length("_text")).alias("size")
    firsts = stage(keyed.groupBy("_th", "_t2").agg(F.min("_id").alias("id"), F.count("*").alias("copies"), size).select(F.col("_th").alias("th"), "_t2", "id", "copies", "size"), "texts")
    n_texts, n_bytes = firsts.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    parts = blobs.parts_for(docs.sparkSession, n_bytes, PART_BYTES)
    found = stage(candidates(keyed.select(F.col("_th").alias("th"), F.col("_text").alias("text")), scheme, n_texts, parts), "anchors")
    hot = np.frombuffer(b"".join(bytes(r.hot) for r in found.where("part = -1").select("hot").collect()), np.uint64)
    wanted = firsts.join(by_text(found, parts), "th").select("id", "th", "firsts")
    rows = keyed.select(F.col("_id").alias("id"), F.col("_th").alias("th"), F.col("_text").alias("text")).join(wanted, ["id", "th"])
    before = rows
    scheme, rows = scheme.named(rows, parts)
    passes = 1
    if scheme.piece_bytes:
        n_anchors = found.where("part >= 0").agg(F.coalesce(F.sum(F.octet_length("first")), F.lit(0))).first()[0] // 4
        passes = passes_for(n_bytes, n_anchors, scheme.piece_bytes)
    if passes > 1 and rows is before:
        rows = stage(rows, "suspects", compression="zstd")
        tidy(docs.sparkSession, found)
    spans, kept = repeated_spans(rows, scheme, hot, parts, passes)
    spans = spans.withColumnsRenamed({"starts": "_starts", "stops": "_stops"})
    known = stage(firsts.join(spans, ["id", "th"], "left"), "spans").select(F.col("id").alias("_id"), F.col("th").alias("_th"), "_t2", "copies", "_starts", "_stops", F.lit(True).alias("_first"))
    tidy(docs.sparkSession, firsts, found, *kept, *([rows] if rows is not before else []))
    return keyed.join(known, ["_id", "_th", "_t2"], "left")
