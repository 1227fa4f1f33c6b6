"""SimHash near-duplicates: fingerprints, and a binary-trie self-join under a Hamming budget.

The join walks pairs of trie nodes together.  A pair carries the number of bits
in which its two prefixes differ, and is dropped as soon as that exceeds the
budget.  The upper part of the walk deals fingerprints out to pairs of trie
leaves (the trie is split wherever a node holds more than `leaf` fingerprints,
so one dense region becomes many leaves); the lower part runs inside a task
over sorted arrays.  A task returns a spanning forest of the links it finds,
never all pairs of a dense group, and copies count once.

Nulls: a null text is an empty one.  Null ids are allowed; a component's id is
its least id that is not null.  Texts without words share fingerprint zero and
link like any other.  Repeated rows are returned as often as they occur.  Other
columns of docs are not returned and cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.llm import blobs
from jointsem.llm.components import components
from jointsem.llm.store import stage
from jointsem.llm.text import Words, mix, slices, space_table

SHINGLE = 3
BUDGET = 2
STEP = 4
CHUNK = 1 << 17
BRUTE = 48
#: Bytes of a dealt fingerprint, and of those that a task gets.
ROW_BYTES, PART_BYTES = 17, 64 << 20
#: A fingerprint with over this share of all rows is joined by broadcast; there are at most as many as its inverse.
HOT_SHARE = 1e-4
_COLUMNS = {"unit": np.uint64, "fp": np.uint64, "side": np.uint8}


def text_fingerprints(texts: list[bytes], shingle: int = SHINGLE) -> np.ndarray:
    """One unsigned 64-bit SimHash per text."""
    words = Words(texts, space_table(), lower=True)
    sizes = words.ends - words.starts
    keep = np.zeros(len(words.data), bool)
    data = words.data
    if len(words):
        keep[:] = space_table()[data]
        keep[words.ends] = True
        data = data.copy()
        data[words.ends] = 0x20
    joined = data[keep].tobytes()
    stops = np.cumsum(sizes + 1) - 1
    begins = stops - sizes
    count = np.diff(words.first)
    grams = np.where(count == 0, 0, np.maximum(1, count - shingle + 1))
    first = np.repeat(words.first[:-1], grams) + np.arange(grams.sum()) - np.repeat(np.cumsum(grams) - grams, grams)
    last = np.minimum(first + shingle, np.repeat(words.first[1:], grams)) - 1
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(joined[a:b], 42) for a, b in zip(begins[first].tolist(), stops[last].tolist(), strict=True)], np.uint64)
    out = np.zeros(len(texts), np.uint64)
    some = np.flatnonzero(grams)
    if len(some):
        bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        sums = np.add.reduceat(bits, (np.cumsum(grams) - grams)[some], axis=0, dtype=np.int32)
        out[some] = np.packbits(2 * sums > grams[some][:, None], axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp): the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(text_fingerprints(texts).view(np.int64))], names=["id", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, fp long")


def dense_prefixes(fps: DataFrame, leaf: int) -> list[np.ndarray]:
    """For each depth in steps, the prefixes (right-aligned) of trie nodes with over `leaf` fingerprints: at most rows / leaf each."""
    found = [np.zeros(1, np.uint64)]
    for depth in range(STEP, 64, STEP):
        prefix = F.shiftrightunsigned(F.col("fp"), 64 - depth)
        dense = fps.groupBy(prefix.alias("prefix")).count().where(F.col("count") > leaf).select("prefix").toPandas()["prefix"].to_numpy(np.int64)
        if not len(dense):
            break
        found.append(np.sort(dense.view(np.uint64)))
    return found


def _contains(sorted_values: np.ndarray, x: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(sorted_values, x), len(sorted_values) - 1)
    return sorted_values[at] == x


def leaves_near(fp: np.ndarray, dense: list[np.ndarray], budget: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, leaf, own): every trie leaf whose prefix is within the budget of a fingerprint's; own marks the one that holds it."""
    masks = np.array([m for m in range(1 << STEP) if m.bit_count() <= budget], np.uint64)
    cost = np.bitwise_count(masks).astype(np.int64)
    row, prefix, spent = np.arange(len(fp)), np.zeros(len(fp), np.uint64), np.zeros(len(fp), np.int64)
    rows, leaves, own = [], [], []
    for level in range(64 // STEP):
        depth = STEP * (level + 1)
        bits = (fp[row] >> np.uint64(64 - depth)) & np.uint64((1 << STEP) - 1)
        total = spent[:, None] + cost[None, :]
        at, which = np.nonzero(total <= budget)
        row, spent, prefix = row[at], total[at, which], (prefix[at] << np.uint64(STEP)) | (bits[at] ^ masks[which])
        inner = _contains(dense[level + 1], prefix) if level + 1 < len(dense) else np.zeros(len(prefix), bool)
        done = ~inner
        rows.append(row[done])
        leaves.append(mix(prefix[done] ^ np.uint64((depth * 0xD1B54A32D192ED03) % 2**64)))
        own.append(spent[done] == 0)
        row, prefix, spent = row[inner], prefix[inner], spent[inner]
        if not len(row):
            break
    return np.concatenate(rows), np.concatenate(leaves), np.concatenate(own)


def _spread(dense: list[np.ndarray]) -> int:
    """A bound on the leaves near a fingerprint: as many as prefixes of the trie's mean depth within two bits of its own."""
    depth = STEP * len(dense)
    return 1 + depth + depth * (depth - 1) // 2


def _split(fp: np.ndarray, lo: np.ndarray, hi: np.ndarray, bit: int) -> np.ndarray:
    """First index of each sorted range whose fingerprint has the bit set, all higher bits being equal in a range."""
    lo, hi, one = lo.copy(), hi.copy(), np.uint64(bit)
    for _ in range(int((hi - lo).max(initial=0)).bit_length()):
        mid = (lo + hi) >> 1
        live = lo < hi
        up = live & ((fp[np.minimum(mid, len(fp) - 1)] >> one & np.uint64(1)) == 0)
        lo, hi = np.where(up, mid + 1, lo), np.where(live & ~up, mid, hi)
    return lo


def trie_pairs(fp: np.ndarray, a0: np.ndarray, a1: np.ndarray, b0: np.ndarray, b1: np.ndarray, same: np.ndarray, budget: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within the budget, between sorted ranges a and b of fp; where same, a and b are one range and pairs are unordered."""
    todo = [(63, a0, a1, b0, b1, same, np.zeros(len(a0), np.int64))]
    while todo:
        bit, a0, a1, b0, b1, same, spent = todo.pop()
        small = (a1 - a0) * (b1 - b0) <= BRUTE if bit >= 0 else np.ones(len(a0), bool)
        if small.any():
            yield from _brute(fp, a0[small], a1[small], b0[small], b1[small], same[small], budget)
            a0, a1, b0, b1, same, spent = (x[~small] for x in (a0, a1, b0, b1, same, spent))
        if not len(a0):
            continue
        am = _split(fp, a0, a1, bit)
        bm = np.where(same, am, _split(fp, b0, b1, bit))
        kids = [(a0, am, b0, bm, same, spent), (am, a1, bm, b1, same, spent), (a0, am, bm, b1, same & False, spent + 1), (am, a1, b0, bm, same & False, spent + 1 + same * 64)]
        joined = [np.concatenate(x) for x in zip(*kids, strict=True)]
        alive = (joined[0] < joined[1]) & (joined[2] < joined[3]) & (joined[5] <= budget)
        joined = [x[alive] for x in joined]
        for at in range(0, len(joined[0]), CHUNK):
            todo.append((bit - 1, *(x[at : at + CHUNK] for x in joined)))


def _brute(fp: np.ndarray, a0: np.ndarray, a1: np.ndarray, b0: np.ndarray, b1: np.ndarray, same: np.ndarray, budget: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for at in range(0, len(a0), CHUNK):
        c0, c1, d0, d1, s = (x[at : at + CHUNK] for x in (a0, a1, b0, b1, same))
        wide = d1 - d0
        each = (c1 - c0) * wide
        unit = np.repeat(np.arange(len(c0)), each)
        k = np.arange(len(unit)) - np.repeat(np.cumsum(each) - each, each)
        i, j = c0[unit] + k // wide[unit], d0[unit] + k % wide[unit]
        ok = (np.bitwise_count(fp[i] ^ fp[j]) <= budget) & (~s[unit] | (i < j))
        if ok.any():
            yield i[ok], j[ok]


def _union(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Merge the sets of i and j in place; a label is the least index of its set."""
    while True:
        a, b = label[i], label[j]
        differ = a != b
        if not differ.any():
            return
        i, j = i[differ], j[differ]
        np.minimum.at(label, np.maximum(a, b)[differ], np.minimum(a, b)[differ])
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label[:] = up


def links(fps: DataFrame, budget: int = BUDGET, leaf: int | None = None) -> DataFrame:
    """Distinct fingerprints (fp) -> (u, v) whose components are those of all links at `budget` or fewer differing bits."""
    spark = fps.sparkSession
    n = fps.count()
    if leaf is None:
        leaf = min(1_000_000, max(8192, n // 1024))
    dense = dense_prefixes(fps, leaf)
    parts = blobs.parts_for(spark, n * ROW_BYTES * _spread(dense), PART_BYTES)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            every = batch.column(0).to_numpy().view(np.uint64)
            for at in range(0, len(every), CHUNK):
                fp = every[at : at + CHUNK]
                row, leaf_id, own = leaves_near(fp, dense, budget)
                home = np.zeros(len(fp), np.uint64)
                home[row[own]] = leaf_id[own]
                mine = home[row]
                unit = mix(np.minimum(mine, leaf_id) ^ mix(np.maximum(mine, leaf_id)))
                yield blobs.pack(blobs.part_of(unit, parts), {"unit": unit, "fp": fp[row], "side": np.where(own, 2, mine < leaf_id).astype(np.uint8)})

    def work(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((x["fp"], x["side"], x["unit"]))
        unit, fp, side = x["unit"][order], x["fp"][order], x["side"][order]
        first = np.flatnonzero(np.append(True, unit[1:] != unit[:-1]))
        last = np.append(first[1:], len(unit))
        mid = first + np.add.reduceat(side == 0, first)
        same = side[first] == 2
        a1, b0 = np.where(same, last, mid), np.where(same, first, mid)
        values, number = np.unique(fp, return_inverse=True)
        label = np.arange(len(values))
        for i, j in trie_pairs(fp, first, a1, b0, last, same, budget):
            _union(label, number[i], number[j])
        child = np.flatnonzero(label != np.arange(len(label)))
        yield pa.RecordBatch.from_arrays([pa.array(values[child].view(np.int64)), pa.array(values[label[child]].view(np.int64))], names=["u", "v"])

    dealt = fps.select("fp").mapInArrow(deal, blobs.schema(_COLUMNS))
    return blobs.reduce_parts(dealt, parts, _COLUMNS, work, "u long, v long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", budget: int = BUDGET) -> DataFrame:
    """(id_col, fp, component_id) for every row; component_id is the least id reachable over links."""
    rows = stage(fingerprints(docs, id_col, text_col), "fingerprints")
    classes = stage(rows.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("copies")), "classes")
    roots = components(links(classes, budget)).select(F.col("node").alias("fp"), "root")
    rooted = classes.join(roots, "fp", "left").select("fp", "least", "copies", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    of_class = stage(rooted.join(least, "root").select("fp", "copies", "component_id"), "members")
    # the copies of a frequent text are not brought together: its class is sent to them
    many = F.col("copies") > HOT_SHARE * classes.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    hot = of_class.where(many).select("fp", F.col("component_id").alias("hot_id"), F.lit(True).alias("hot"))
    marked = rows.join(F.broadcast(hot), "fp", "left")
    near = marked.where("hot").select("id", "fp", F.col("hot_id").alias("component_id"))
    far = marked.where("hot is null").select("id", "fp").join(of_class.where(~many).select("fp", "component_id"), "fp")
    return near.unionByName(far).select(F.col("id").alias(id_col), "fp", "component_id")
