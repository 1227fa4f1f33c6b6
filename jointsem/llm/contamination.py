"""Benchmark decontamination by winnowing.

Both sides keep the least k-gram hash of every window of WINDOW - K + 1
neighbouring k-grams, so a shared span of WINDOW words always shares a kept
fingerprint.  An item of fewer than WINDOW words is one window; its fingerprint
is the hash of all its words, and documents keep the hashes of all their windows
of that size.

The documents' fingerprints are joined with the benchmark's.  A bit table of the
benchmark's, of a fixed size, goes to the documents' tasks first, so that few
others are sent into the join; a benchmark too large for a table of use is joined
without one.  Only documents with a common fingerprint are read again: each hit is
extended to the whole windows around it, and these are compared word by word with
the items of the blocks that the join names.  A block holds items of bounded
bytes, whatever the benchmark holds, and sees only documents that share a
fingerprint with it.

Nulls: a null text has no words; a null item id is written as an empty string.
Items with equal ids count once.  Repeated rows are returned as often as they
occur.  An empty benchmark leaves every document clean.  Of a column of docs that
has the name of a result, the result stays.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.llm.store import stage
from jointsem.llm.text import Prefix, Words, alnum_table, merged, mix, sliding_min, slices, starts_of_runs

WINDOW = 13
K = 6
BLOCK_BYTES = 16 << 20
#: Up to so many fingerprints of the benchmark are told to the tasks as a table of 16 bytes each (64 MB).
SIEVE_PRINTS = 4 << 20
_MADE = ("n_words", "starts", "stops", "items", "n_hit", "n_items", "items_sha256", "contaminated")
_SIEVE_BITS = 20


def _gram_hashes(prefix: Prefix, k: int) -> np.ndarray:
    return mix(prefix.grams(k) + np.uint64(k))


class _Set:
    """A sorted set of hashes with a small bit table before it."""

    def __init__(self, values: np.ndarray):
        self.values = np.unique(values)
        self.sieve = np.zeros(1 << _SIEVE_BITS, bool)
        self.sieve[self.values & np.uint64((1 << _SIEVE_BITS) - 1)] = True

    def where(self, h: np.ndarray) -> np.ndarray:
        at = np.flatnonzero(self.sieve[h & np.uint64((1 << _SIEVE_BITS) - 1)])
        return at[self.find(h[at]) >= 0] if len(at) else at

    def find(self, h: np.ndarray) -> np.ndarray:
        if not len(self.values):
            return np.full(len(h), -1)
        i = np.minimum(np.searchsorted(self.values, h), len(self.values) - 1)
        return np.where(self.values[i] == h, i, -1)


def _winnow(grams: np.ndarray, first: np.ndarray, count: np.ndarray, width: int) -> np.ndarray:
    """Positions of the least gram of every window of `width` grams inside one text; first and count give each text's words."""
    if len(grams) < width:
        return np.zeros(0, np.int64)
    low = np.uint64((1 << 24) - 1)
    tagged = (grams & ~low) | (np.arange(len(grams), dtype=np.uint64) & low)
    least = sliding_min(tagged, width)
    span = width + K - 1
    ok = np.zeros(len(least) + 1, np.int64)
    some = count >= span
    np.add.at(ok, first[some], 1)
    np.add.at(ok, np.minimum(first[some] + count[some] - span + 1, len(least)), -1)
    starts = np.flatnonzero(np.cumsum(ok[:-1]) > 0)
    at = (least[starts] & low).astype(np.int64)
    if len(grams) > 1 << 24:  # positions wrap; the high part is that of the window
        at |= starts & ~((1 << 24) - 1)
        at += np.where(at < starts, 1 << 24, 0)
    return at[starts_of_runs(at)] if len(at) else at


def _spelled(text: bytes, starts: np.ndarray, ends: np.ndarray, w: int, n: int) -> bytes:
    return b" ".join([text[a:b] for a, b in zip(starts[w : w + n].tolist(), ends[w : w + n].tolist(), strict=True)])


class Windows:
    """The windows of n words of a block: one class per hash, with a place to read its words and its items."""

    def __init__(self, words: Words, text: bytes, codes: Prefix, n: int, of: np.ndarray):
        h = _gram_hashes(codes, n)
        at = np.flatnonzero(of[words.doc[: len(h)]] & (words.doc[: len(h)] == words.doc[n - 1 :][: len(h)]))
        order = at[np.lexsort((words.doc[at], h[at]))]
        new = starts_of_runs(h[order])
        self.n, self.known = n, _Set(h[order])
        self.place = order[new]
        self.rare: dict[bytes, set[int]] = {}
        own = np.cumsum(new) - 1
        keep = starts_of_runs(own, words.doc[order])
        for i in np.flatnonzero(~new).tolist():
            spelled = _spelled(text, words.starts, words.ends, order[i], n)
            if spelled != _spelled(text, words.starts, words.ends, self.place[own[i]], n):
                self.rare.setdefault(spelled, set()).add(int(words.doc[order[i]]))
                keep[i] = False
        self.items = words.doc[order][keep]
        self.first = np.searchsorted(own[keep], np.arange(len(self.place) + 1))


class Index:
    """A block of benchmark items: kept fingerprints, and windows with the items they are from."""

    def __init__(self, rows: list[tuple[str, bytes]]):
        words = Words([t for _, t in rows], alnum_table(), lower=True)
        codes = Prefix(words.hashes())
        count = np.diff(words.first)
        self.ids = [i for i, _ in rows]
        self.text, self.starts, self.ends = words.data.tobytes(), words.starts, words.ends
        lengths = np.minimum(count, WINDOW)
        self.windows = [Windows(words, self.text, codes, n, lengths == n) for n in np.unique(lengths[lengths > 0]).tolist()]
        grams = _gram_hashes(codes, K)
        self.prints = _Set(grams[_winnow(grams, words.first[:-1], count, WINDOW - K + 1)])


def find(index: Index, texts: list[bytes]) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray, list[str]]]]:
    """Word counts, and for each text the hit word spans and the sorted ids of the items with a window in it."""
    words = Words(texts, alnum_table(), lower=True)
    count = np.diff(words.first)
    codes = Prefix(words.hashes())
    text = b""
    items: dict[int, set[str]] = {}
    spans: dict[int, list[tuple[int, int]]] = {}
    for of in index.windows:
        n, h = of.n, _gram_hashes(codes, of.n)
        if n == WINDOW:
            grams = _gram_hashes(codes, K)
            kept = _winnow(grams, words.first[:-1], count, WINDOW - K + 1)
            seeds = kept[index.prints.where(grams[kept])]
            near = np.unique((seeds[:, None] - np.arange(WINDOW - K + 1)).ravel())
            near = near[(near >= 0) & (near < len(h))]
        else:
            near = of.known.where(h)
        near = near[words.doc[near] == words.doc[near + n - 1]]
        place = of.known.find(h[near])
        for w, k in zip(near[place >= 0].tolist(), place[place >= 0].tolist(), strict=True):
            text = text or words.data.tobytes()
            spelled = _spelled(text, words.starts, words.ends, w, n)
            if spelled == _spelled(index.text, index.starts, index.ends, of.place[k], n):
                found = of.items[of.first[k] : of.first[k + 1]].tolist()
            else:
                found = of.rare.get(spelled, ())
            if found:
                d = int(words.doc[w])
                items.setdefault(d, set()).update(index.ids[i] for i in found)
                spans.setdefault(d, []).append((w - words.first[d], w - words.first[d] + n))
    none = np.zeros(0, np.int64)
    out = [(none, none, [])] * len(texts)
    for d, found in items.items():
        a, b = np.array(spans[d]).T
        out[d] = (*merged(a, b), sorted(found))
    return count, out


def item_prints(rows: list[bytes]) -> list[tuple[int, np.ndarray]]:
    """(size, fingerprints) of items: WINDOW for the winnowed ones, else the words of a short item."""
    words = Words(rows, alnum_table(), lower=True)
    codes, count = Prefix(words.hashes()), np.diff(words.first)
    grams = _gram_hashes(codes, K)
    out = [(WINDOW, np.unique(grams[_winnow(grams, words.first[:-1], count, WINDOW - K + 1)]))]
    for n in np.unique(count[(count > 0) & (count < WINDOW)]).tolist():
        out.append((n, np.unique(codes.span(words.first[:-1][count == n], words.first[:-1][count == n] + n))))
    return [(n, _sized(n, h) if n < WINDOW else h) for n, h in out if len(h)]


def _sized(n: int, h: np.ndarray) -> np.ndarray:
    return mix(h ^ np.uint64(n * 0x9E3779B97F4A7C15 % 2**64))


def text_prints(texts: list[bytes], sizes: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word counts of the texts, their fingerprints that an item could share, and the text of each."""
    words = Words(texts, alnum_table(), lower=True)
    codes, count = Prefix(words.hashes()), np.diff(words.first)
    owner, found = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)]
    for n in sizes:
        if n == WINDOW:
            grams = _gram_hashes(codes, K)
            at = _winnow(grams, words.first[:-1], count, WINDOW - K + 1)
            h = grams[at]
        else:
            at = np.arange(max(0, len(words) - n + 1))
            at = at[words.doc[at] == words.doc[at + n - 1]]
            h = _sized(n, codes.span(at, at + n))
        owner.append(words.doc[at])
        found.append(h)
    return count, np.concatenate(found), np.concatenate(owner)


def hits(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", block_bytes: int = BLOCK_BYTES, carry: bool = False, sieve: int = SIEVE_PRINTS) -> DataFrame:
    """id, n_words, starts and stops (hit word spans), items (ids found, sorted); with carry, also every column of docs."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    items = benchmark.select(F.coalesce(F.col(item_col).cast("string"), F.lit("")).alias("item"), text.alias("text"))
    n_blocks = -(-int(items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]) // block_bytes) or 1
    items = stage(items.withColumn("block", F.pmod(F.xxhash64("item", "text"), F.lit(n_blocks)).cast("int")), "items")
    prints = stage(_bench_prints(items), "prints")
    sizes = sorted(r.size for r in prints.select("size").distinct().collect())
    shared = spark.sparkContext.broadcast(_table(prints, sieve))
    own = [c for c in docs.columns if c not in _MADE] if carry else []
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("h"), F.col(text_col).cast("string").alias("text"), *[F.col(c).alias(f"_{n}") for n, c in enumerate(own)])
    kept = rows.schema.fields[3:]

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            count, h, owner = text_prints(texts, sizes)
            if shared.value is not None:
                at = np.flatnonzero(shared.value[h & np.uint64(len(shared.value) - 1)])
                h, owner = h[at], owner[at]
            order = np.argsort(owner, kind="stable")
            lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(owner[order], np.arange(len(texts) + 1)).astype(np.int32)), pa.array(h[order].view(np.int64)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(count), lists, *batch.columns[3:]], names=["id", "h", "n_words", "prints", *batch.schema.names[3:]])

    read = rows.mapInArrow(keep, "id long, h long, n_words long, prints array<long>" + "".join(f", {f.name} {f.dataType.simpleString()}" for f in kept))
    held = read.where("size(prints) > 0").select("id", "h", F.explode(F.array_distinct("prints")).alias("print"))
    near = stage(held.join(prints.select("print", "block").distinct(), "print").select("id", "h", "block").distinct(), "candidates")
    texts = stage(rows.select("id", "h", "text").join(near.select(F.col("id").alias("i"), F.col("h").alias("k")).distinct(), F.col("id").eqNullSafe(F.col("i")) & F.col("h").eqNullSafe(F.col("k")), "left_semi").dropDuplicates(["id", "h"]), "candidate_texts")
    found = None
    for r in near.select("block").distinct().orderBy("block").collect():
        more = _compared(texts, near.where(F.col("block") == r.block), items.where(F.col("block") == r.block))
        found = more if found is None else found.unionByName(more)
    spans = "array<int>"
    if found is None:
        out = read.select("*", F.array().cast(spans).alias("starts"), F.array().cast(spans).alias("stops"), F.array().cast("array<string>").alias("items"))
    else:
        each = found.groupBy(F.col("id").alias("i"), F.col("h").alias("k")).agg(*[F.flatten(F.collect_list(c)).alias(c) for c in ("starts", "stops", "items")])
        done = stage(each.withColumn("items", F.array_sort(F.array_distinct("items"))), "hits")
        none = lambda c, kind: F.coalesce(c, F.array().cast(kind)).alias(c)
        both = read.join(done, F.col("id").eqNullSafe(F.col("i")) & F.col("h").eqNullSafe(F.col("k")), "left")
        out = both.select(*read.columns, none("starts", spans), none("stops", spans), none("items", "array<string>"))
    if carry:
        return out.drop("id", "h", "prints").withColumnsRenamed({f"_{n}": c for n, c in enumerate(own)})
    return out.drop("h", "prints").withColumnRenamed("id", id_col)


def _bench_prints(items: DataFrame) -> DataFrame:
    """(print, size, block) of the benchmark, distinct."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            block = batch.column(1).to_numpy()
            for b in np.unique(block).tolist():
                for n, h in item_prints([t for t, own in zip(texts, block.tolist(), strict=True) if own == b]):
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(np.full(len(h), n, np.int32)), pa.array(np.full(len(h), b, np.int32))], names=["print", "size", "block"])

    return items.select("text", "block").mapInArrow(run, "print long, size int, block int").distinct()


def _table(prints: DataFrame, limit: int) -> np.ndarray | None:
    """A bit (here: a byte) for each value of the low bits of the prints, 16 a print; None if there are more than `limit` prints."""
    n = prints.count()
    if n > limit:
        return None
    table = np.zeros(1 << max(10, (16 * n).bit_length()), bool)
    h = prints.select("print").toArrow().column("print").to_numpy().view(np.uint64)
    table[h & np.uint64(len(table) - 1)] = True
    return table


def _compared(texts: DataFrame, near: DataFrame, items: DataFrame) -> DataFrame:
    """id, h, starts, stops, items of the candidate texts of a block that hold windows of its items."""
    rows = [(r.item, (r.text or "").encode()) for r in items.orderBy("item", "text").toLocalIterator()]
    shared = texts.sparkSession.sparkContext.broadcast(Index(rows))
    spans, names = pa.list_(pa.int32()), pa.list_(pa.string())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, part in slices(batches):
            _, found = find(shared.value, part)
            new = [pa.array([x[0] for x in found], spans), pa.array([x[1] for x in found], spans), pa.array([x[2] for x in found], names)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], *new], names=["id", "h", "starts", "stops", "items"])

    wanted = near.select(F.col("id").alias("i"), F.col("h").alias("k"))
    mine = texts.join(wanted, F.col("id").eqNullSafe(F.col("i")) & F.col("h").eqNullSafe(F.col("k")), "left_semi")
    return mine.select("id", "h", "text").mapInArrow(run, "id long, h long, starts array<int>, stops array<int>, items array<string>").where("size(items) > 0")


def n_hit() -> Column:
    """Words under the spans of hits(), which may overlap where several blocks met."""
    pairs = "array_sort(arrays_zip(starts, stops))"
    return F.expr(f"aggregate({pairs}, struct(0L as n, 0 as e), (s, x) -> struct(s.n + greatest(0, x.stops - greatest(x.starts, s.e)) as n, greatest(s.e, x.stops) as e), s -> s.n)")


def judged(found: DataFrame) -> DataFrame:
    """hits() with n_hit, n_items, items_sha256 and contaminated (at least a twentieth of the words hit)."""
    return (
        found.withColumn("n_hit", n_hit())
        .withColumn("n_items", F.size("items").cast("long"))
        .withColumn("items_sha256", F.sha2(F.array_join("items", ","), 256))
        .withColumn("contaminated", F.expr("n_hit > 0 and 20 * n_hit >= n_words"))
    )
