"""Toxicity by a subsequence string-kernel SVM with Nyström landmarks.

The kernel of two units (words, or spelled-out runs of single letters) compares
their symbol triples, in order but with gaps; the symbols are a unit's letters
with one mark at either end, and ASCII characters that are no letters are passed
over.  A triple that spans n symbols weighs DECAY ** (n - 3), up to SPAN symbols,
and the kernel is the cosine of these weights.  So dots or repeated letters put
into an insult change its similarity little or not at all.  A sentence's
similarity to a landmark is that of its closest unit, similarities under FLOOR
counting as zero; a sentence is mapped by the inverse root of the landmarks'
kernel matrix, and a linear SVM scores it.  A document's margin is that of its
worst sentence.

Labels that no single unit carries are learned from how often kindred units
recur.  Over the training texts that the kernel leaves on the clean side, the
openings of units (their first LEAD bytes of letters, of any script) pool the
evidence of all units that begin so.  The opening and least share of a text's
units that tell most about the label are taken, the texts they cover set aside,
and so on while the gain stands out among all openings tried.  A second linear
SVM scores the shares.  Both margins become log odds by fitted sigmoids, the
greater one counts, and a last sigmoid makes it a score.

Words whose similarity cannot reach FLOOR are recognised by an upper bound that
needs one table look-up per triple; only the others are compared in full.

The model is fitted on a sample of labelled rows, at most `sample` per class in
the order of a hash of the id; every document is scored whole.  Nulls: a null
text is empty and scores like a sentence without insults; rows with a null
label or id train nothing.  Without both classes every score is the share of
toxic labels (0.5 / (n + 1) smoothed).
"""

from __future__ import annotations

import itertools
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from jointsem.llm.text import Words, gather, slices, space_table, starts_of_runs

DECAY = 0.7
SPAN = 6
FLOOR = 0.75
LANDMARKS = 64
LEAST_GAIN = 0.25
LEAD = range(3, 9)
#: Least share of toxic texts among those with a unit similar to a landmark; what tells less by its mere presence is left to the openings.
DECISIVE = 0.75
#: Log of how much rarer than once per fit a chance choice of a landmark or an opening is to be.
SURETY = 5.0
FEW = 3
CHUNK = 1 << 16
SAMPLE = 4000
_CLASSES = 28
_MARK = 27
_TABLE = _CLASSES**3
_GAPS = [(a, b) for b in range(2, SPAN) for a in range(1, b)]
_LETTER = np.zeros(256, np.int64)
_LETTER[97:123] = np.arange(1, 27)
_ENDS = np.zeros(256, bool)
_ENDS[list(b".!?;:")] = True


def triples(flat: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(unit, triple, weight) of every gapped symbol triple of units flat[start : start + size]; letters are lower-case."""
    raw = gather(flat, start, size)
    unit = np.repeat(np.arange(len(size)), size)
    kept = (_LETTER[raw] > 0) | (raw >= 0x80)
    raw, unit = raw[kept], unit[kept]
    count = np.bincount(unit, minlength=len(size))
    room = count + 2 + SPAN
    begin = np.cumsum(room) - room
    code = np.zeros(int(room.sum()) + SPAN, np.int64)
    code[begin], code[begin + count + 1] = _MARK, _MARK
    code[np.repeat(begin + 1 - (np.cumsum(count) - count), count) + np.arange(len(unit))] = _LETTER[raw]
    place = np.flatnonzero(code)
    unit = np.searchsorted(begin, place, "right") - 1
    lead = code[place]
    out = []
    for a, b in _GAPS:
        x, y = code[place + a], code[place + b]
        ok = (x > 0) & (y > 0)
        out.append((unit[ok], (lead[ok] * _CLASSES + x[ok]) * _CLASSES + y[ok], np.full(int(ok.sum()), DECAY ** (b - 2))))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def unit_vectors(words: list[bytes]) -> np.ndarray:
    """Normalised triple weights of a few units, one row each."""
    size = np.array([len(w) for w in words], np.int64)
    unit, triple, weight = triples(np.frombuffer(b"".join(words), np.uint8), np.cumsum(size) - size, size)
    out = np.zeros((len(words), _TABLE))
    np.add.at(out, (unit, triple), weight)
    return out / np.maximum(np.sqrt((out * out).sum(axis=1, keepdims=True)), 1e-12)


class Units:
    """The distinct units of a slice, and where they occur."""

    def __init__(self, texts: list[bytes]):
        words = Words(texts, space_table(), lower=True)
        self.n_docs = len(texts)
        data, extra, owner = words.data, [], []
        size = words.ends - words.starts
        one = (size == 1) & (_LETTER[data[words.starts]] > 0) if len(words) else np.zeros(0, bool)
        if one.any():
            at = np.flatnonzero(one)
            new = np.ones(len(at), bool)
            new[1:] = (np.diff(at) > 1) | (words.doc[at[1:]] != words.doc[at[:-1]])
            head = np.flatnonzero(new)
            for i, n in zip(head.tolist(), np.diff(np.append(head, len(at))).tolist(), strict=True):
                if n >= 3:
                    extra.append(data[words.starts[at[i : i + n]]].tobytes())
                    owner.append(int(at[i]))
        more = np.array([len(x) for x in extra], np.int64)
        self.flat = np.concatenate([data, np.frombuffer(b"".join(extra), np.uint8)])
        start = np.concatenate([words.starts, len(data) + np.cumsum(more) - more]).astype(np.int64)
        size = np.concatenate([size, more]).astype(np.int64)
        word = np.concatenate([np.arange(len(words)), np.array(owner, np.int64)]).astype(np.int64)
        key = np.concatenate([words.hashes(), np.arange(len(extra), dtype=np.uint64)])
        _, first, self.number = np.unique(key, return_index=True, return_inverse=True)
        self.number = self.number.ravel()
        self.start, self.size = start[first], size[first]
        self.doc = words.doc[word]
        lines = np.cumsum(data == 10)
        stop = np.zeros(len(words), np.int64)
        if len(words):
            ends = _ENDS[data[words.ends - 1]][:-1] | (lines[words.starts[1:]] != lines[words.ends[:-1]]) | (words.doc[1:] != words.doc[:-1])
            stop[1:] = np.cumsum(ends)
        self.sentence = stop[word]

    def spelled(self, k: int) -> bytes:
        return self.flat[self.start[k] : self.start[k] + self.size[k]].tobytes()

    def leads(self) -> np.ndarray:
        """The first eight bytes of each unit's letters as a number, zeros at the end; ASCII characters that are no letters are passed over."""
        raw, unit = gather(self.flat, self.start, self.size), np.repeat(np.arange(len(self.size)), self.size)
        kept = (_LETTER[raw] > 0) | (raw >= 0x80)
        raw, unit = raw[kept], unit[kept]
        count = np.bincount(unit, minlength=len(self.size))
        place = np.arange(len(unit)) - (np.cumsum(count) - count)[unit]
        out = np.zeros((len(self.size), 8), np.uint8)
        out[unit[place < 8], place[place < 8]] = raw[place < 8]
        return out.view(">u8").ravel().astype(np.uint64)


class Kernel:
    """Similarities to fixed landmarks."""

    def __init__(self, landmarks: list[bytes]):
        self.landmarks = landmarks
        self.table = np.ascontiguousarray(unit_vectors(landmarks).T)
        self.bound = self.table.max(axis=1) if landmarks else np.zeros(_TABLE)

    def similar(self, units: Units) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the units with a similarity of FLOOR or more, and their similarities (below FLOOR: 0)."""
        unit, triple, weight = triples(units.flat, units.start, units.size)
        n = len(units.size)
        top = np.bincount(unit, weight * self.bound[triple], n)
        norm = np.sqrt(np.bincount(unit, weight * weight, n))
        able = top >= FLOOR * norm - 1e-9
        able[norm == 0] = False
        keep = able[unit]
        unit, triple, weight = unit[keep], triple[keep], weight[keep]
        if not len(unit):
            return np.zeros(0, np.int64), np.zeros((0, self.table.shape[1]))
        cell, where = np.unique(unit * _TABLE + triple, return_inverse=True)
        value = np.bincount(where.ravel(), weight)
        row, triple = cell // _TABLE, cell % _TABLE
        head = np.flatnonzero(starts_of_runs(row))
        length = np.sqrt(np.add.reduceat(value * value, head))
        k, each = np.empty((len(head), self.table.shape[1])), max(1, CHUNK // self.table.shape[1])
        stop = np.append(head, len(row))
        for i in range(0, len(head), each):
            a, b = head[i], stop[min(i + each, len(head))]
            k[i : i + each] = np.add.reduceat(value[a:b, None] * self.table[triple[a:b]], head[i : i + each] - a, axis=0) / length[i : i + each, None]
        k[k < FLOOR] = 0
        some = (k > 0).any(axis=1)
        return row[head][some], k[some]

    def sentences(self, units: Units) -> tuple[np.ndarray, np.ndarray]:
        """Text of, and similarities of, each sentence that is similar to a landmark."""
        number, k = self.similar(units)
        row = np.full(len(units.size), -1)
        row[number] = np.arange(len(number))
        at = np.flatnonzero(row[units.number] >= 0)
        if not len(at):
            return at, np.zeros((0, self.table.shape[1]))
        at = at[np.argsort(units.sentence[at], kind="stable")]
        head = np.flatnonzero(starts_of_runs(units.sentence[at]))
        return units.doc[at][head], np.maximum.reduceat(k[row[units.number[at]]], head, axis=0)


def _opening(lead: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The opening of n bytes of each lead, and which leads have one."""
    low = np.uint64(8 * (8 - n))
    cut = lead >> low
    return cut << low, cut & np.uint64(255) > 0


@dataclass
class Openings:
    """Openings of units with the share of a text's units from which each tells, and an SVM over the shares."""

    opening: np.ndarray
    size: np.ndarray
    least: np.ndarray
    weight: np.ndarray
    offset: float = -np.inf

    def graded(self, units: Units) -> np.ndarray:
        """For each text and opening its share over the least share, at most 2, and the sum of all, at most 4."""
        lead, m = units.leads(), len(self.opening)
        total = np.maximum(np.bincount(units.doc, minlength=units.n_docs), 1)
        out = np.zeros((units.n_docs, m + 1))
        for n in np.unique(self.size).tolist():
            mine = np.flatnonzero(self.size == n)
            mine = mine[np.argsort(self.opening[mine])]
            cut, able = _opening(lead, n)
            at = np.minimum(np.searchsorted(self.opening[mine], cut), len(mine) - 1)
            of = np.where(able & (self.opening[mine][at] == cut), mine[at], -1)[units.number]
            held = of >= 0
            out += np.bincount(units.doc[held] * (m + 1) + of[held], minlength=out.size).reshape(out.shape)
        out[:, :m] /= total[:, None] * self.least
        out[:, m] = np.minimum(out[:, :m].sum(axis=1), 4)
        return np.minimum(out, [*[2] * m, 4])

    def margins(self, units: Units) -> np.ndarray:
        return self.graded(units) @ self.weight + self.offset if len(self.opening) else np.full(units.n_docs, -np.inf)


@dataclass
class Scorer:
    kernel: Kernel
    weight: np.ndarray
    offset: float
    slope: float
    level: float
    openings: Openings | None = None

    def margins(self, texts: list[bytes]) -> np.ndarray:
        units = Units(texts)
        doc, k = self.kernel.sentences(units)
        out = np.full(len(texts), self.offset)
        np.maximum.at(out, doc, k @ self.weight + self.offset)
        return np.maximum(out, self.openings.margins(units)) if self.openings else out

    def all_margins(self, texts: list[bytes]) -> np.ndarray:
        return np.concatenate([self.margins(texts[i : i + 64]) for i in range(0, len(texts), 64)])

    def scores(self, texts: list[bytes]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.margins(texts) + self.level, -35, 35)))


def _landmarks(texts: list[bytes], toxic: np.ndarray, n: int) -> list[bytes]:
    """The units of toxic texts whose presence tells most about the label, by the likelihood ratio of their document counts, if that stands out among all units tried (or, with few texts, is not far below the best) and holds for similar units as well."""
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    for t, y in zip(texts, toxic, strict=True):
        units = Units([t])
        letters = np.add.reduceat(_LETTER[gather(units.flat, units.start, units.size)] > 0, np.cumsum(units.size) - units.size) if len(units.size) else units.size
        for k in np.flatnonzero(letters >= 4).tolist():
            seen[int(y)][bytes(c for c in units.spelled(k) if 97 <= c <= 122)] += 1
    total = np.array([np.sum(toxic == 0), np.sum(toxic == 1)], float)
    able = [w for w, c in seen[1].items() if c / total[1] > seen[0][w] / total[0] and c >= min(3, total[1])]
    gains = dict(zip(able, _gain(np.array([seen[0][w] for w in able], float), np.array([seen[1][w] for w in able], float), *total).tolist(), strict=True))
    least = min(np.log(max(1, len(seen[1]))) + SURETY, LEAST_GAIN * max(gains.values(), default=0))
    likely = sorted((w for w in able if gains[w] >= least), key=lambda w: (-gains[w], w))
    chosen: list[bytes] = []
    while likely and len(chosen) < n:
        some, likely = likely[:n], likely[n:]
        kernel, held = Kernel(some), np.zeros((2, len(some)))
        for i in range(0, len(texts), 64):
            doc, k = kernel.sentences(Units(texts[i : i + 64]))
            row, col = np.nonzero(k)
            cell = np.unique(doc[row] * len(some) + col)
            np.add.at(held, (toxic[i + cell // len(some)], cell % len(some)), 1)
        chosen += [w for w, clean, bad in zip(some, *held, strict=True) if bad >= DECISIVE * (clean + bad)]
    return chosen[:n]


def _gain(clean: np.ndarray, bad: np.ndarray, all_clean: float, all_bad: float) -> np.ndarray:
    """Log-likelihood ratio of the label where a mark that clean and bad texts hold is met."""
    share = (clean + bad) / (all_clean + all_bad)
    return bad * np.log(np.maximum(bad, 1e-9) / (all_bad * share)) + clean * np.log(np.maximum(clean, 1e-9) / np.maximum(all_clean * share, 1e-9))


def _shares(texts: list[bytes], wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, number of the wanted opening, share of the text's units), by opening and falling share."""
    docs, numbers, shares = [np.zeros(0, np.int32)], [np.zeros(0, np.int32)], [np.zeros(0, np.float32)]
    for i in range(0, len(texts), 64):
        units = Units(texts[i : i + 64])
        total = np.bincount(units.doc, minlength=units.n_docs)
        for n, cut in _held(units):
            at = np.minimum(np.searchsorted(wanted, cut), len(wanted) - 1)
            at = np.where(wanted[at] == cut, at, -1)[units.number]
            cell, times = np.unique(units.doc[at >= 0] * len(wanted) + at[at >= 0], return_counts=True)
            docs.append((cell // len(wanted) + i).astype(np.int32))
            numbers.append((cell % len(wanted)).astype(np.int32))
            shares.append((times / total[cell // len(wanted)]).astype(np.float32))
    doc, number, share = np.concatenate(docs), np.concatenate(numbers), np.concatenate(shares)
    del docs, numbers, shares
    order = np.lexsort((-share, number)).astype(np.int32)
    return doc[order], number[order], share[order]


def _held(units: Units) -> Iterator[tuple[int, np.ndarray]]:
    """For each size of opening that of every distinct unit, 0 for shorter units."""
    lead = units.leads()
    for n in LEAD:
        cut, able = _opening(lead, n)
        yield n, np.where(able, cut, np.uint64(0))


def _candidates(texts: list[bytes], least: int) -> tuple[np.ndarray, int]:
    """The openings that at least so many texts hold, and how many there are in all."""
    seen, times = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    for i in range(0, len(texts), 64):
        new = []
        units = Units(texts[i : i + 64])
        for _, cut in _held(units):
            names, number = np.unique(cut, return_inverse=True)
            cell = np.unique(units.doc * len(names) + number.ravel()[units.number])
            new.append(names[cell % max(1, len(names))])
        both = np.concatenate([seen, *new])
        weight = np.concatenate([times, np.ones(len(both) - len(seen), np.int64)])
        seen, at = np.unique(both, return_inverse=True)
        times = np.bincount(at.ravel(), weight, len(seen)).astype(np.int64)
    real = seen > 0
    return seen[real & (times >= least)], int(real.sum())


def _best(doc: np.ndarray, number: np.ndarray, share: np.ndarray, toxic: np.ndarray, left: np.ndarray) -> tuple[float, int, int]:
    """The greatest gain of an opening and least share, and the rows from and to which the texts it covers lie."""
    found, start = (0.0, 0, 0), 0
    while start < len(doc):
        stop = min(len(doc), start + CHUNK)
        stop = int(np.searchsorted(number, number[stop - 1], "right"))
        mine = slice(start, stop)
        head = np.flatnonzero(starts_of_runs(number[mine]))
        run = np.repeat(head, np.diff(np.append(head, stop - start)))
        above = np.append(0, np.cumsum(toxic[doc[mine]]))
        bad = (above[1:] - above[run]).astype(float)
        clean = np.arange(1, stop - start + 1) - run - bad
        gain = _gain(clean, bad, *left)
        last = np.append((np.diff(number[mine]) != 0) | (np.diff(share[mine]) != 0), True)
        gain[~last | (bad * left[0] <= clean * left[1]) | (bad < FEW)] = 0
        at = int(np.argmax(gain))
        found = max(found, (float(gain[at]), start + int(run[at]), start + at + 1), key=lambda x: x[0])
        start = stop
    return found


def _openings(texts: list[bytes], toxic: np.ndarray) -> Openings | None:
    """Openings that tell the toxic texts from the others, chosen one by one over the texts that those before do not cover; None if none stands out."""
    wanted, tried = _candidates([texts[i] for i in np.flatnonzero(toxic == 1)], FEW)
    if not len(wanted):
        return None
    doc, number, share = _shares(texts, wanted)
    covered, chosen = np.zeros(len(texts), bool), []
    while len(doc) and len(chosen) < LANDMARKS:
        left = np.array([np.sum(~covered & (toxic == 0)), np.sum(~covered & (toxic == 1))], float)
        if not left.all():
            break
        gain, start, stop = _best(doc, number, share, toxic, left)
        if gain < np.log(tried) + SURETY:
            break
        opening = wanted[number[start]]
        chosen.append((opening, int(sum(b > 0 for b in int(opening).to_bytes(8, "big"))), float(share[stop - 1])))
        covered[doc[start:stop]] = True
        keep = ~covered[doc]
        doc, number, share = doc[keep], number[keep], share[keep]
    if not chosen:
        return None
    made = Openings(np.array([c[0] for c in chosen], np.uint64), np.array([c[1] for c in chosen]), np.array([c[2] for c in chosen]), np.zeros(0))
    x = np.concatenate([made.graded(Units(texts[i : i + 64])) for i in range(0, len(texts), 64)])
    weight, offset = _svm(x, toxic, np.ones(len(x)))
    slope, level = _sigmoid(x @ weight + offset, toxic)
    made.weight, made.offset = slope * weight, slope * offset + level
    return made


def fit(texts: list[bytes], toxic: np.ndarray, landmarks: int = LANDMARKS) -> Scorer:
    """A scorer from labelled texts.  A sentence has the label of its text; sentences like no landmark count once per text without others."""
    share = (toxic.sum() + 0.5) / (len(toxic) + 1)
    constant = Scorer(Kernel([]), np.zeros(0), 0.0, 0.0, float(np.log(share / (1 - share))))
    if not 0 < toxic.sum() < len(toxic):
        return constant
    chosen = _landmarks(texts, toxic, landmarks)
    scorer = _worst_sentence(texts, toxic, chosen) if chosen else Scorer(Kernel([]), np.zeros(0), constant.level, 1.0, 0.0)
    margin = scorer.all_margins(texts)
    if chosen:
        slope, level = _sigmoid(margin, toxic)
        scorer.weight, scorer.offset = slope * scorer.weight, slope * scorer.offset + level
        margin = scorer.all_margins(texts)
    rest = np.flatnonzero(margin < 0)
    scorer.openings = _openings([texts[i] for i in rest], toxic[rest])
    if not chosen and not scorer.openings:
        return constant
    scorer.slope, scorer.level = _sigmoid(scorer.all_margins(texts), toxic)
    return scorer


def _worst_sentence(texts: list[bytes], toxic: np.ndarray, chosen: list[bytes]) -> Scorer:
    kernel = Kernel(chosen)
    values, vectors = np.linalg.eigh(kernel.table.T @ kernel.table)
    root = vectors @ np.diag(1 / np.sqrt(np.maximum(values, 1e-6))) @ vectors.T
    doc, k = [], []
    for i in range(0, len(texts), 64):
        d, s = kernel.sentences(Units(texts[i : i + 64]))
        doc.append(d + i)
        k.append(s)
    doc, k = np.concatenate(doc), np.concatenate(k)
    bare = np.setdiff1d(np.arange(len(texts)), doc)
    owner = np.concatenate([doc, bare])
    x = np.concatenate([k @ root, np.zeros((len(bare), len(chosen)))])
    weight, offset = _svm(x, toxic[owner], 1 / np.bincount(owner)[owner])
    return Scorer(kernel, root @ weight, offset, 1.0, 0.0)


def _svm(x: np.ndarray, toxic: np.ndarray, share: np.ndarray, c: float = 1e-4) -> tuple[np.ndarray, float]:
    """A linear SVM with class-balanced squared hinge loss of rows weighted by share, by Newton steps on the rows inside the margin."""
    y = np.where(toxic == 1, 1.0, -1.0)
    each = 0.5 * share / np.where(y > 0, share[y > 0].sum(), share[y < 0].sum())
    full = np.concatenate([x, np.ones((len(x), 1))], axis=1)
    ridge = np.diag([*[c] * x.shape[1], 1e-9])
    w = np.zeros(full.shape[1])

    def loss(v: np.ndarray) -> float:
        return float(each @ np.maximum(0, 1 - y * (full @ v)) ** 2 + v @ ridge @ v)

    for _ in range(100):
        inside = y * (full @ w) < 1
        rows = full[inside] * each[inside][:, None]
        step = np.linalg.solve(rows.T @ full[inside] + ridge, rows.T @ y[inside]) - w
        size = 1.0
        while loss(w + size * step) > loss(w) and size > 1e-6:
            size /= 2
        w = w + size * step
        if size * np.abs(step).max() < 1e-9:
            break
    return w[:-1], float(w[-1])


def _sigmoid(margin: np.ndarray, toxic: np.ndarray) -> tuple[float, float]:
    """Slope and level of the sigmoid that fits the labels best, by Newton steps on smoothed targets."""
    good, bad = (toxic == 1).sum(), (toxic == 0).sum()
    target = np.where(toxic == 1, (good + 1) / (good + 2), 1 / (bad + 2))
    a = np.array([1.0, 0.0])
    x = np.stack([margin, np.ones(len(margin))], axis=1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ a, -35, 35)))
        hessian = (x * (p * (1 - p))[:, None]).T @ x + 1e-6 * np.eye(2)
        step = np.linalg.solve(hessian, x.T @ (target - p))
        a = a + np.clip(step, -2, 2)
    return max(0.0, float(a[0])), float(a[1])


def remainder(id_col: str) -> Column:
    """crc32 of the id as text, modulo 5."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 5


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", held_out: int = 0) -> Scorer:
    """A scorer from at most `sample` labelled rows of each class whose remainder is not held_out."""
    usable = labels.where((remainder("doc_id") != held_out) & F.col("toxic").isin(0, 1)).select(F.col("doc_id").alias("_label_id"), F.col("toxic").alias("_toxic"))
    wanted = [usable.where(F.col("_toxic") == y).orderBy(F.xxhash64("_label_id"), "_label_id").limit(sample) for y in (0, 1)]
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text")).join(F.broadcast(wanted[0].unionByName(wanted[1])), F.col("_id") == F.col("_label_id")).orderBy("_id", "_text").select("_text", "_toxic").toArrow()
    texts = [(t or "").encode() for t in rows.column("_text").to_pylist()]
    return fit(texts, np.array(rows.column("_toxic").to_pylist(), np.int64))


def score_documents(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> DataFrame:
    """id, held_out, score and predicted for every row of docs."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels, sample, id_col, text_col))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(remainder(id_col) == 0, F.lit(False)).alias("held_out"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = shared.value
        for batch, texts in slices(batches):
            score = scorer.scores(texts)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], names=["id", "held_out", "score", "predicted"])

    return rows.mapInArrow(run, "id long, held_out boolean, score double, predicted int").withColumnRenamed("id", id_col)


def similarity(a: str, b: str) -> float:
    """The kernel of two units."""
    x, y = unit_vectors([a.lower().encode(), b.lower().encode()])
    return float(x @ y)


def plain_similarity(a: str, b: str) -> float:
    """The kernel by enumeration, for tests."""

    def weights(s: str) -> Counter:
        out: Counter = Counter()
        symbols = ["<", *(c for c in s.lower().encode() if 97 <= c <= 122 or c >= 128), ">"]
        for i, j, k in itertools.combinations(range(len(symbols)), 3):
            if k - i < SPAN and all(symbols[m] in ("<", ">") or symbols[m] <= 122 for m in (i, j, k)):
                out[tuple("|" if symbols[m] in ("<", ">") else symbols[m] for m in (i, j, k))] += DECAY ** (k - i - 2)
        return out

    x, y = weights(a), weights(b)
    norm = (sum(v * v for v in x.values()) * sum(v * v for v in y.values())) ** 0.5
    return sum(v * y[t] for t, v in x.items()) / norm if norm else 0.0
