"""Scoring by an n-gram model kept in a log-frequency Bloom filter.

The filter holds, for each n-gram of the training texts, the events (n-gram, 1)
to (n-gram, q), where q is its quantised log count: 1 + floor(log_BASE count).
A count is read by probing for 1, 2, ... until a probe misses; a probe of an
absent n-gram hits with a small probability, and rarely twice.  Probabilities
interpolate bigram and unigram estimates from these counts.

The filter grows with the corpus, so no worker could hold it as one.  It consists
of segments chosen by n-gram hash, and it is the probes that travel: texts are
packed into blocks, each block sends the distinct n-grams of its texts, with how
often its training texts hold them, to the segments' tasks.  A segment's task
sums these counts, builds the segment, probes it for every n-gram it was sent and
answers each block with the levels found.  Nothing is left out, whatever the size:
more text makes more segments, and a task holds one segment and its probes.

The base score needs exact counts; the same answers carry those of the tokens.

Tokens are told apart by 64-bit hashes.  Nulls: a null text is empty, so its one
token is the end; a null id has no remainder and trains.  Without training
tokens the scores are null.  Repeated rows train and are returned as often as they
occur.  Only the id and the columns named in score() are returned, so other
columns of docs cannot clash.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.llm import blobs
from jointsem.llm.store import stage
from jointsem.llm.text import SLICE_BYTES, Words, mix, slices, space_table, starts_of_runs

BASE = 1.5
PROBES = 6
BITS = 10
WEIGHT = 0.4
TRUST = 5
MAX_LEVEL = 64
#: Text of a block, and what the probes of a segment's task take, in bytes.
BLOCK_BYTES = 1 << 20
PART_BYTES = 24 << 20
CHUNK = 1 << 17
SHORT = 5
_SPACES = (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r")
_END = np.uint64(0x2545F4914F6CDD1D)
_ORDER = np.uint64(0x9E6C63D0876A9A47)
_ASKED = {"t": "binary", "t0": "int", "t1": "int", "tn": "binary", "p": "binary", "p0": "int", "p1": "int", "pn": "binary"}


def pieces(text: bytes, limit: int = SLICE_BYTES) -> Iterator[bytes]:
    """A text cut between words, into pieces of about `limit` bytes; a longer word is a piece."""
    start = 0
    while len(text) - start > limit:
        at = max(text.rfind(c, start, start + limit) for c in _SPACES)
        if at <= start:
            at = min((k for c in _SPACES if (k := text.find(c, start + limit)) >= 0), default=len(text))
        yield text[start:at]
        start = at
    yield text[start:]


def tokens(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of the texts, each text's words and then one end, and where each text starts.

    Hashing takes many times the bytes it reads, so it reads pieces of bounded bytes at a time.
    """
    held, owner, hashes, docs, size = [], [], [], [], 0

    def flush() -> None:
        words = Words(held, space_table(), lower=True)
        hashes.append(words.hashes())
        docs.append(np.array(owner, np.int64)[words.doc])
        held.clear()
        owner.clear()

    for d, text in enumerate(texts):
        for piece in pieces(text):
            if held and size + len(piece) > SLICE_BYTES:
                flush()
                size = 0
            held.append(piece)
            owner.append(d)
            size += len(piece)
    if held:
        flush()
    doc = np.concatenate([np.zeros(0, np.int64), *docs])
    first = np.append(0, np.cumsum(np.bincount(doc, minlength=len(texts)) + 1))
    out = np.full(first[-1], _END)
    out[np.arange(len(doc)) + doc] = np.concatenate([np.zeros(0, np.uint64), *hashes])
    return out, first


def bigrams(codes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Hash of each token with the one before it; a text's first token follows an end."""
    before = np.full(len(codes), _END)
    before[1:] = codes[:-1]
    before[first[:-1]] = _END
    return mix((mix(before + _ORDER) + codes) ^ _ORDER)


def level(count: np.ndarray) -> np.ndarray:
    """Quantised log count: 1 for 1, and one more for each factor of BASE."""
    return np.minimum(MAX_LEVEL, 1 + np.floor(np.log(np.maximum(count, 1)) / np.log(BASE) + 1e-9)).astype(np.int64)


def typical(q: np.ndarray) -> np.ndarray:
    """The count a level stands for: the middle of its whole counts, 0 for level 0."""
    low = np.ceil(BASE ** (q - 1.0) - 1e-9)
    return np.where(q <= 0, 0.0, np.where(q == 1, 1.0, (low + np.maximum(low, np.ceil(BASE ** (q * 1.0) - 1e-9) - 1)) / 2))


class Filter:
    """One segment: a table of bits whose number is a power of two."""

    def __init__(self, bits: np.ndarray):
        self.bits, self.mask = bits, np.uint64(8 * len(bits) - 1)

    def levels(self, h: np.ndarray) -> np.ndarray:
        """The level of every n-gram: how many probes in a row hit."""
        return np.concatenate([self._levels(h[i : i + CHUNK]) for i in range(0, len(h), CHUNK)] or [np.zeros(0, np.uint8)])

    def _levels(self, h: np.ndarray) -> np.ndarray:
        out = np.zeros(len(h), np.uint8)
        at = np.arange(len(h))
        for q in range(1, MAX_LEVEL + 1):
            step = mix(h[at] + _turn(q))
            hit = np.arange(len(at))
            for k in range(PROBES):
                bit = _probe(step[hit], k) & self.mask
                hit = hit[self.bits[(bit >> np.uint64(3)).astype(np.int64)] >> (bit & np.uint64(7)).astype(np.uint8) & 1 > 0]
            if not len(hit):
                break
            at = at[hit]
            out[at] = q
        return out


def _turn(q: int) -> np.uint64:
    return np.uint64(q * int(_ORDER) % 2**64)


def _probe(step: np.ndarray, k: int) -> np.ndarray:
    return step + np.uint64(k) * ((step >> np.uint64(31)) | np.uint64(1))


def segment(h: np.ndarray, count: np.ndarray) -> Filter:
    """The filter segment of n-grams with counts: BITS bits per event or up to twice as many."""
    q = level(count).astype(np.uint8)
    bits = 1 << max(6, (int(q.sum(dtype=np.int64)) * BITS - 1).bit_length())
    table = np.zeros(bits, bool)
    for i in range(0, len(h), CHUNK):
        own, least = h[i : i + CHUNK], q[i : i + CHUNK]
        for n in range(1, int(least.max()) + 1):
            step = mix(own[least >= n] + _turn(n))
            for k in range(PROBES):
                table[(_probe(step, k) & np.uint64(bits - 1)).astype(np.int64)] = True
    return Filter(np.packbits(table, bitorder="little"))


def trains(id_col: str) -> Column:
    """True for rows the model learns from; crc32 of the id as text, modulo 5, is not 1."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 != 1, F.lit(True))


def blocks(docs: DataFrame, id_col: str, text_col: str, limit: int = BLOCK_BYTES) -> DataFrame:
    """docs packed into rows of about `limit` bytes of text: (block, n_bytes, ids, held, texts).

    A block's name is drawn at random and kept, for the table is written before it is read.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), (~trains(id_col)).alias("held"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slices(batches, limit=limit):
            whole = pa.array([0, part.num_rows], pa.int32())
            lists = [pa.ListArray.from_arrays(whole, part.column(k).cast(kind)) for k, kind in enumerate((pa.int64(), pa.bool_(), pa.binary()))]
            yield pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().hex]), pa.array([sum(map(len, texts))], pa.int64()), *lists], names=["block", "n_bytes", "ids", "held", "texts"])

    return stage(rows.mapInArrow(run, "block string, n_bytes long, ids array<long>, held array<boolean>, texts array<binary>"), "blocks")


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[list]:
    """Rows one by one, for one of them is large."""
    for batch in batches:
        for r in range(batch.num_rows):
            yield [c[r].as_py() for c in batch.columns]


class _Grams:
    """Tokens and pairs of a block: occurrences, and the distinct ones in the order in which they are asked for.

    Distinct ones are ordered by part, then by whether the block's training texts
    hold them never, once or more often, so that only the last need their counts.
    """

    def __init__(self, texts: list[bytes], held: list[bool], parts: int):
        self.codes, self.first = tokens(texts)
        learns = np.repeat(~np.array(held, bool), np.diff(self.first))
        self.token = _Distinct(self.codes, learns, parts)
        self.pair = _Distinct(bigrams(self.codes, self.first), learns, parts)


class _Distinct:
    def __init__(self, codes: np.ndarray, learns: np.ndarray, parts: int):
        known, of = np.unique(codes, return_inverse=True)
        of = of.ravel()
        count = np.bincount(of[learns], minlength=len(known)).astype(np.int32)
        cell = blobs.part_of(known, parts).astype(np.int64) * 3 + np.minimum(count, 2)
        order = np.argsort(cell, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.key, self.count, self.cell, self.of = known[order], count[order], cell[order], place[of]

    def cut(self, part: np.ndarray) -> tuple[np.ndarray, ...]:
        """Where the keys of each part begin, where its once held ones and its others begin, and where it ends."""
        return tuple(np.searchsorted(self.cell, 3 * part + k) for k in range(4))


def _short(key: np.ndarray) -> np.ndarray:
    """The low five bytes of each key.  A segment's pairs differ in these but for about one in a million; the filter's own false hits are one in a hundred."""
    return np.ascontiguousarray(key.view(np.uint8).reshape(-1, 8)[:, :SHORT])


def _long(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // SHORT, 8), np.uint8)
    out[:, :SHORT] = np.frombuffer(data, np.uint8).reshape(-1, SHORT)
    return out.view(np.uint64).ravel()


def _asked(table: DataFrame, parts: int) -> DataFrame:
    """Each block's n-grams with their training counts, one row for each segment asked; t0, t1 and p0, p1 are how many are held never and once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, held, texts in _rows(batches):
            g = _Grams(texts, held, parts)
            wanted = np.unique(np.concatenate([g.token.cell, g.pair.cell]) // 3)
            data = []
            for x, key in ((g.token, g.token.key), (g.pair, _short(g.pair.key))):
                a, b, c, d = x.cut(wanted)
                data.append(pa.array([key[i:j].tobytes() for i, j in zip(a, d, strict=True)], pa.binary()))
                data += [pa.array((b - a).astype(np.int32)), pa.array((c - b).astype(np.int32))]
                data.append(pa.array([x.count[i:j].tobytes() for i, j in zip(c, d, strict=True)], pa.binary()))
            yield pa.RecordBatch.from_arrays([pa.array(wanted.astype(np.int32)), pa.array([block] * len(wanted)), *data], names=["part", "block", *_ASKED])

    return table.select("block", "held", "texts").mapInArrow(run, "part int, block string, " + ", ".join(f"{c} {kind}" for c, kind in _ASKED.items()))


def _counts(keys: np.ndarray, size: np.ndarray, never: np.ndarray, once: np.ndarray, more: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys, their summed counts, and the place of each key among them; the keys of a row are those held never, once and more often, in this order."""
    step = np.arange(len(keys), dtype=np.int32) - np.repeat((np.cumsum(size) - size).astype(np.int32), size)
    count = (step >= np.repeat(never.astype(np.int32), size)).astype(np.int32)
    count[step >= np.repeat((never + once).astype(np.int32), size)] = np.frombuffer(more, np.int32)
    del step
    order = np.argsort(keys).astype(np.int32)
    known = keys[order]
    new = starts_of_runs(known)
    place = np.empty(len(keys), np.int32)
    place[order] = np.cumsum(new, dtype=np.int32) - 1
    head = np.flatnonzero(new)
    return known[head], np.add.reduceat(count[order], head, dtype=np.int64) if len(head) else np.zeros(0, np.int64), place


def _answers(asked: DataFrame, parts: int) -> DataFrame:
    """For each block and segment the tokens' exact counts and levels and the pairs' levels; a row without a block has the segment's training tokens, all and distinct."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {c: [] for c in ("part", "block", *_ASKED)}
        for batch in batches:
            for k, c in enumerate(held):
                held[c] += batch.column(k).to_pylist()
        part, names = held.pop("part"), held.pop("block")
        if not names:
            return
        ints = lambda c: np.array(held[c], np.int64)
        size_t, size_p = np.array([len(x) // 8 for x in held["t"]]), np.array([len(x) // SHORT for x in held["p"]])
        token, n, of_token = _counts(np.frombuffer(b"".join(held.pop("t")), np.uint64), size_t, ints("t0"), ints("t1"), b"".join(held.pop("tn")))
        pair, m, of_pair = _counts(_long(b"".join(held.pop("p"))), size_p, ints("p0"), ints("p1"), b"".join(held.pop("pn")))
        filter_ = segment(np.concatenate([token[n > 0], pair[m > 0]]), np.concatenate([n[n > 0], m[m > 0]]))
        of_tokens, of_pairs = filter_.levels(token), filter_.levels(pair)
        del token, pair, m
        data = []
        for values, size in ((n[of_token], size_t), (of_tokens[of_token], size_t), (of_pairs[of_pair], size_p)):
            stop = np.append(0, np.cumsum(size))
            data.append(pa.array([values[i:j].tobytes() for i, j in zip(stop[:-1], stop[1:], strict=True)], pa.binary()))
        none, columns = pa.array([0] * len(names), pa.int64()), ["block", "part", "tc", "tl", "pl", "n", "v"]
        yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(part, pa.int32()), *data, none, none], names=columns)
        blank = pa.array([b""], pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.string()), pa.array(part[:1], pa.int32()), blank, blank, blank, pa.array([int(n.sum())]), pa.array([int((n > 0).sum())])], names=columns)

    return asked.repartitionById(parts, F.col("part")).mapInArrow(run, "block string, part int, tc binary, tl binary, pl binary, n long, v long")


@dataclass(frozen=True)
class Model:
    """What every block needs besides its answers: training tokens, all and distinct."""

    total: int
    distinct: int

    def base(self, count: np.ndarray) -> np.ndarray:
        return np.log10((count + 0.5) / (self.total + 0.5 * (self.distinct + 1)))

    def log_probabilities(self, single: np.ndarray, pair: np.ndarray, first: np.ndarray, end: float) -> np.ndarray:
        """log10 of a mixture of the bigram share and the unigram estimate; the share weighs WEIGHT, and less after a token of few counts.

        single and pair are the counts that the levels of each token, and of it with the one before, stand for; end is that of the end.
        """
        before = np.empty(len(single))
        before[1:] = single[:-1]
        before[first[:-1]] = end
        unigram = (single + 0.5) / (self.total + 0.5 * (self.distinct + 1))
        share = np.where(before > 0, np.minimum(pair, np.minimum(before, single)) / np.maximum(before, 1), 0)
        weight = WEIGHT * before / (before + TRUST)
        return np.log10(weight * share + (1 - weight) * unigram)


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES, part_bytes: int = PART_BYTES) -> tuple[Model, DataFrame, DataFrame, int]:
    """The model of the training rows of docs, the blocks of all rows, the answers to each block, and the number of segments."""
    table = blocks(docs, id_col, text_col, block_bytes)
    size = table.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    parts = blobs.parts_for(docs.sparkSession, 2 * size, part_bytes)
    answers = stage(_answers(_asked(table, parts), parts), "levels")
    total = answers.where("block is null").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("v"), F.lit(0))).first()
    return Model(*map(int, total)), table, answers, parts


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES, part_bytes: int = PART_BYTES) -> DataFrame:
    """id, held_out, n_tokens, n_known, train_tokens, base_score and score for every row of docs."""
    model, table, answers, parts = train(docs, id_col, text_col, block_bytes, part_bytes)
    n = blobs.parts_for(docs.sparkSession, table.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0], 8 * block_bytes)
    of_block = answers.where("block is not null").repartition(n, "block").groupBy("block").agg(F.array_sort(F.collect_list(F.struct("part", "tc", "tl", "pl"))).alias("found"))
    both = table.select("block", "ids", "held", "texts").repartition(n, "block").join(of_block, "block").select("ids", "held", "texts", *[F.expr(f"transform(found, x -> x.{c})").alias(c) for c in ("tc", "tl", "pl")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, held, texts, *found in _rows(batches):
            g = _Grams(texts, held, parts)
            count, single, pair = (np.frombuffer(b"".join(x), kind) for x, kind in zip(found, (np.int64, np.uint8, np.uint8), strict=True))
            count, single, pair = count[g.token.of], typical(single)[g.token.of], typical(pair)[g.pair.of]
            doc = np.repeat(np.arange(len(texts)), np.diff(g.first))
            add = lambda v, at=doc, n=len(texts): np.bincount(at, v, n)
            if model.total:
                base, value = add(model.base(count)), add(model.log_probabilities(single, pair, g.first, float(single[g.first[1] - 1])))
            else:
                base = value = np.full(len(texts), np.nan)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(held), pa.array(np.diff(g.first)), pa.array(add(count > 0).astype(np.int64)), pa.array(base), pa.array(value)], names=["id", "held_out", "n_tokens", "n_known", "base_score", "score"])

    scored = both.mapInArrow(run, "id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    null = lambda c: F.when(~F.isnan(c), F.col(c)).alias(c)
    return scored.select(F.col("id").alias(id_col), "held_out", "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), null("base_score"), null("score"))
