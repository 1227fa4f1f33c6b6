"""Recompression of word sequences: rounds that name runs and pairs of symbols.

A round first names every maximal run of one symbol, then splits the alphabet by
a bit of the symbols' names into left and right ones and names every left-right
pair.  Words, runs and pairs get 64-bit hashes for provisional names; they decide
the structure, so that equal strings are cut alike everywhere.  A round of Spark
then collects the definitions of a level's names from all texts (the word, the
symbol and length of a run, the two symbols of a pair) and gives further names to
definitions that share one.  So the names the next round builds on are exact: a
name stands for one string, and equal names verify equal words.

With each symbol goes the span of words that fixes it: its own words and those
neighbours that were looked at.  A symbol whose span lies inside a repeated
passage appears in every copy of that passage, at the same place.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from jointsem.llm.text import Prefix, gather, mix

ROUNDS = 3
_RUN, _PAIR = np.uint64(0xA0761D6478BD642F), np.uint64(0xE7037ED1A0B428DB)
_SHORT_RUN = np.uint64(0x8BB84B93962EACC9)


@dataclass
class Symbols:
    """Symbols in order: provisional and exact name, text, own words [start, stop), and the words [low, high) that fix each; low or high is outside the text if its edge was looked at."""

    name: np.ndarray
    exact: np.ndarray
    doc: np.ndarray
    start: np.ndarray
    stop: np.ndarray
    low: np.ndarray
    high: np.ndarray


@dataclass
class Definitions:
    """What a level's names stand for: kind, name, first word, and bytes flat[at : at + size] of each."""

    kind: int
    name: np.ndarray
    word: np.ndarray
    at: np.ndarray
    size: np.ndarray
    flat: np.ndarray

    def take(self, rows: np.ndarray) -> Definitions:
        return Definitions(self.kind, self.name[rows], self.word[rows], self.at[rows], self.size[rows], self.flat)


@dataclass
class Names:
    """Names of the definitions that share a hash, by kind and hash; all others are named by their hash.

    Of n definitions about n ** 2 / 2 ** 65 share one, so this stays small.  Hashes of fewer bits are for tests.
    """

    table: dict[int, dict[int, dict[bytes, int]]] = field(default_factory=dict)
    bits: int = 64

    def cut(self, h: np.ndarray) -> np.ndarray:
        return h & np.uint64(2**self.bits - 1)

    def add(self, kind: int, name: int, definitions: list[bytes]) -> None:
        """Name further definitions; the names that some of them have already stay."""
        known = self.table.setdefault(kind, {}).setdefault(name, {})
        for d in sorted(definitions):
            if d not in known:
                known[d] = name if not known else int(mix(np.array([(name + len(known) * int(_SHORT_RUN)) % 2**64], np.uint64))[0])

    def resolve(self, d: Definitions) -> np.ndarray:
        shared = self.table.get(d.kind)
        if not shared:
            return d.name
        out = d.name.copy()
        for i in np.flatnonzero(np.isin(d.name, np.array(list(shared), np.uint64))).tolist():
            spelled = d.flat[d.at[i] : d.at[i] + d.size[i]].tobytes()
            out[i] = shared[int(d.name[i])].get(spelled, int(d.name[i]))
        return out


def _neighbours(x: Symbols, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """low of the symbol before and high of the symbol after, one word beyond the text where there is none."""
    n = len(x.name)
    low, high = first[x.doc] - 1, first[x.doc + 1] + 1
    if n > 1:
        same = x.doc[1:] == x.doc[:-1]
        low[1:] = np.where(same, x.low[:-1], low[1:])
        high[:-1] = np.where(same, x.high[1:], high[:-1])
    return low, high


def _name_runs(x: Symbols, first: np.ndarray, kind: int, names: Names, define: bool) -> tuple[Symbols, Definitions | None]:
    head = np.ones(len(x.name), bool)
    head[1:] = (x.name[1:] != x.name[:-1]) | (x.doc[1:] != x.doc[:-1])
    at = np.flatnonzero(head)
    end = np.append(at[1:], len(head)) - 1
    low, high = _neighbours(x, first)
    several = np.flatnonzero(end > at)
    length = (end[several] - at[several] + 1).astype(np.uint64)
    name, made = x.name[at], None
    name[several] = names.cut(mix(name[several] + length * _RUN))
    exact = name
    if define or names.table:
        made = _run_definitions(x, at, several, length, kind, names)
        if names.table:
            exact = x.exact[at]
            exact[several] = names.resolve(made)
    return Symbols(name, exact, x.doc[at], x.start[at], x.stop[end], low[at], high[end]), made


def _run_definitions(x: Symbols, at: np.ndarray, several: np.ndarray, length: np.ndarray, kind: int, names: Names) -> Definitions:
    """A run is defined by its symbol and length; symbols of one provisional name may have several exact ones, and such a run is defined by all of them."""
    start, size = at[several], length.astype(np.int64)
    code = mix(x.exact[start] + length * _RUN)
    place, width = np.arange(len(several)) * 16, np.full(len(several), 16)
    flat = np.stack([x.exact[start], length], axis=1).ravel().view(np.uint8)
    mixed = np.flatnonzero(np.maximum.reduceat(x.exact, at)[several] != np.minimum.reduceat(x.exact, at)[several]) if len(several) else several
    if len(mixed):
        more = gather(x.exact, start[mixed], size[mixed])
        stop = np.cumsum(size[mixed])
        code[mixed] = mix(Prefix(more).span(stop - size[mixed], stop) + _SHORT_RUN)
        place[mixed], width[mixed] = len(flat) + 8 * (stop - size[mixed]), 8 * size[mixed]
        flat = np.concatenate([flat, more.view(np.uint8)])
    return Definitions(kind, names.cut(code), x.start[start], place, width, flat)


def _name_pairs(x: Symbols, first: np.ndarray, salt: int, kind: int, names: Names, define: bool) -> tuple[Symbols, Definitions | None]:
    left = mix(x.name ^ np.uint64(salt * 2 + 1)) >> np.uint64(63) == 0
    pair = np.zeros(len(x.name), bool)
    pair[:-1] = left[:-1] & ~left[1:] & (x.doc[1:] == x.doc[:-1])
    keep = np.ones(len(pair), bool)
    keep[1:] = ~pair[:-1]
    low, high = _neighbours(x, first)
    at, made = np.flatnonzero(pair), None
    name, stop = x.name.copy(), x.stop.copy()
    name[at] = names.cut(mix(mix(x.name[at] + _PAIR) ^ x.name[at + 1]))
    exact = name
    if define or names.table:
        both = np.stack([x.exact[at], x.exact[at + 1]], axis=1).ravel()
        made = Definitions(kind, names.cut(mix(mix(x.exact[at] + _PAIR) ^ x.exact[at + 1])), x.start[at], np.arange(len(at)) * 16, np.full(len(at), 16), both.view(np.uint8))
        if names.table:
            exact = x.exact.copy()
            exact[at] = names.resolve(made)
    low = np.where(left, x.low, low)
    high = np.where(left, high, x.high)
    high[at], stop[at] = x.high[at + 1], x.stop[at + 1]
    name = name[keep]
    return Symbols(name, exact[keep] if names.table else name, x.doc[keep], x.start[keep], stop[keep], low[keep], high[keep]), made


def compress(codes: np.ndarray, exact: np.ndarray, doc: np.ndarray, first: np.ndarray, names: Names, rounds: int = ROUNDS, define: int = 0) -> tuple[Symbols, list[Definitions]]:
    """Symbols after so many rounds over words with provisional codes and exact names, and the definitions of round `define`; first[d] is the first word of text d, first[-1] their number.

    While no definitions share a hash, exact names are the provisional ones.
    """
    at = np.arange(len(codes))
    x, made = Symbols(codes, exact, doc, at, at + 1, at, at + 1), []
    for r in range(1, rounds + 1 if len(codes) else 0):
        x, runs = _name_runs(x, first, 2 * r - 1, names, r == define)
        x, pairs = _name_pairs(x, first, r - 1, 2 * r, names, r == define)
        made += [runs, pairs] if r == define else []
    return x, made


def anchors(codes: np.ndarray, x: Symbols, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash, first, count, symbol): consecutive windows of `width` words of one text that choose the same symbol; -1 for none.

    A window chooses, of the symbols fixed inside it, that with the least hash of
    the words fixing it.  One without such a symbol is its own anchor.  Both
    depend on the window's words alone, so equal windows get equal hashes.
    """
    prefix = Prefix(codes)
    length = np.diff(first)
    edge = np.zeros(len(codes) + 1, np.int64)
    some = length >= width
    np.add.at(edge, first[:-1][some], 1)
    np.add.at(edge, first[1:][some] - width + 1, -1)
    start = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
    if not len(start):
        none = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), none, none, none
    inside = np.flatnonzero((x.low >= first[x.doc]) & (x.high <= first[x.doc + 1]) & (x.high - x.low <= width))
    low, high = x.low[inside], x.high[inside]
    own = mix(prefix.span(low, high) ^ x.name[inside])
    lo, hi = np.searchsorted(low, start), np.searchsorted(high, start + width, "right") - 1
    full = hi >= lo
    bits = np.uint64((1 << max(1, len(own).bit_length())) - 1)
    table = [(own & ~bits) | np.arange(len(own), dtype=np.uint64)]
    step = 1
    while step < int((hi - lo).max(initial=0)) + 1:
        last = table[-1]
        table.append(np.minimum(last[:-step], last[step:]) if len(last) > step else last)
        step *= 2
    chosen = np.full(len(start), -1)
    size = hi[full] - lo[full] + 1
    level = np.int64(np.frexp(size.astype(np.float64))[1] - 1)
    best = np.zeros(len(size), np.uint64)
    for k in np.unique(level).tolist():
        m = level == k
        best[m] = np.minimum(table[k][lo[full][m]], table[k][hi[full][m] - (1 << k) + 1])
    chosen[full] = (best & bits).astype(np.int64)
    new = np.ones(len(start), bool)
    new[1:] = (chosen[1:] != chosen[:-1]) | (chosen[1:] < 0) | (start[1:] != start[:-1] + 1)
    at = np.flatnonzero(new)
    count = np.diff(np.append(at, len(start)))
    alone = chosen[at] < 0
    h = np.where(alone, mix(prefix.span(start[at], start[at] + width) + np.uint64(1)), own[chosen[at]] if len(own) else np.uint64(0))
    return h, start[at], count, np.where(alone, -1, inside[chosen[at]] if len(inside) else -1)
