import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from jointsem.llm import language_model as lm


def toks(text):
    low = re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode())
    return [*re.findall(rb"[^\x20\x09-\x0D]+", low), None]


def held(i):
    return i is not None and zlib.crc32(str(i).encode()) % 5 == 1


def rows():
    rng = random.Random(8)
    vocab = [f"w{i}" for i in range(50)] + ["Été", "x" * 90]
    out = [(i, " ".join(rng.choice(vocab[: 5 + i % 45]) for _ in range(rng.randrange(60))) + (f" only{i}" if i % 3 else "")) for i in range(150)]
    return [*out, (500, None), (501, ""), (502, "\n \t"), (None, "w1 w2 w3"), (0, out[0][1]), (503, "w1 w2 " * 20000)]


@pytest.mark.parametrize("part_bytes", [1 << 26, 1 << 14])
def test_base_score_is_exact(documents, part_bytes):
    data = rows()
    counts = Counter(t for i, x in data if not held(i) for t in toks(x))
    n, v = sum(counts.values()), len(counts)
    got = sorted(((str(r.doc_id), r.n_tokens, r.n_known, r.held_out, r.train_tokens, r.base_score) for r in lm.score(documents(data), block_bytes=1 << 16, part_bytes=part_bytes).collect()), key=str)
    want = sorted(((str(i), len(toks(x)), sum(counts[t] > 0 for t in toks(x)), held(i), n, sum(math.log10((counts[t] + 0.5) / (n + 0.5 * (v + 1))) for t in toks(x))) for i, x in data), key=str)
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert [g[5] for g in got] == pytest.approx([w[5] for w in want])


def test_long_texts_are_hashed_in_pieces(monkeypatch):
    texts = [b"", b"aa b\tccc  d", b" ", b"x" * 50 + b" y z", b"one two three four five six seven"]
    whole = lm.tokens(texts)
    monkeypatch.setattr(lm, "SLICE_BYTES", 8)
    monkeypatch.setattr(lm.pieces, "__defaults__", (8,))
    cut = lm.tokens(texts)
    assert all(len(p) <= 8 or b" " not in p.strip() for t in texts for p in lm.pieces(t)) and all(b"".join(lm.pieces(t)) == t for t in texts)
    assert np.array_equal(whole[0], cut[0]) and np.array_equal(whole[1], cut[1])


def test_filter_returns_levels():
    rng = np.random.default_rng(1)
    h = rng.integers(0, 2**63, 20000, dtype=np.uint64) * np.uint64(2)
    n = np.minimum(rng.zipf(1.7, 20000), 10**6)
    f = lm.segment(h, n)
    got = f.levels(h)
    assert np.all(got >= lm.level(n)) and (got == lm.level(n)).mean() > 0.97
    absent = rng.integers(0, 2**63, 20000, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    assert (f.levels(absent) > 0).mean() < 0.03
    assert np.all(np.abs(lm.typical(lm.level(n)) - n) <= 0.5 * n)


@pytest.mark.parametrize("part_bytes", [1 << 26, 1 << 14])
def test_score_is_that_of_exact_counts_through_the_quantiser(documents, part_bytes):
    """But for false hits of the filter, however many segments it has."""
    data = rows()
    single, pair = Counter(), Counter()
    for i, x in data:
        if not held(i):
            t = toks(x)
            single.update(t)
            pair.update(zip([None, *t[:-1]], t, strict=True))
    total, distinct = sum(single.values()), len(single)

    def coarse(n):
        return float(lm.typical(lm.level(np.array([n])))[0]) if n else 0.0

    def want(x):
        t, out = toks(x), 0.0
        for v, w in zip([None, *t[:-1]], t, strict=True):
            cv, cw, both = coarse(single[v]), coarse(single[w]), coarse(pair[v, w])
            share, weight = (min(both, cv, cw) / cv if cv else 0.0), lm.WEIGHT * cv / (cv + lm.TRUST)
            out += math.log10(weight * share + (1 - weight) * (cw + 0.5) / (total + 0.5 * (distinct + 1)))
        return out

    got = sorted((str(r.doc_id), r.n_tokens, r.score) for r in lm.score(documents(data), block_bytes=1 << 16, part_bytes=part_bytes).collect())
    exact = sorted((str(i), len(toks(x)), want(x)) for i, x in data)
    assert [g[:2] for g in got] == [e[:2] for e in exact]
    gap = sum(abs(g[2] - e[2]) for g, e in zip(got, exact, strict=True))
    assert gap < 0.01 * abs(sum(e[2] for e in exact))


def test_segments_grow_with_the_texts(spark, documents):
    """The number of segments follows the bytes, so that what a task holds does not; nothing is left out."""
    small, large = rows()[:100], rows()[:100] * 20
    parts = []
    for data in (small, large):
        model, _, answers, n = lm.train(documents(data), block_bytes=1 << 12, part_bytes=1 << 12)
        parts.append(n)
        most = answers.groupBy("part").agg({"pl": "count"}).count()
        assert most <= n and model.total == sum(len(toks(x)) for i, x in data if not held(i))
    assert parts[1] >= 10 * parts[0]


def test_model_beats_the_base_on_held_out_texts(documents):
    rng = random.Random(5)
    words = [f"v{i}" for i in range(40)]
    data = []
    for i in range(300):
        t = [rng.choice(words)]
        for _ in range(40):
            t.append(words[(words.index(t[-1]) + rng.choice([1, 2, 3])) % 40])
        data.append((i, " ".join(t)))
    got = [r for r in lm.score(documents(data)).collect() if r.held_out]
    assert len(got) > 20 and all(r.score > r.base_score for r in got) and all(math.isfinite(r.score) and r.score < 0 for r in got)


def test_empty_table_and_no_training_rows(documents):
    assert lm.score(documents([])).collect() == []
    only = next(i for i in range(100) if held(i))
    r = lm.score(documents([(only, "a b")])).collect()[0]
    assert (r.n_tokens, r.n_known, r.train_tokens, r.base_score, r.score) == (3, 0, 0, None, None)


def test_probabilities_sum_to_about_one():
    data = [(i, x) for i, x in rows() if not held(i)]
    single, pair = Counter(), Counter()
    for _, x in data:
        single.update(toks(x))
        pair.update(zip([None, *toks(x)[:-1]], toks(x), strict=True))
    model = lm.Model(sum(single.values()), len(single))
    coarse = lambda n: lm.typical(lm.level(np.array(n)) * (np.array(n) > 0))
    vocab = list(single)
    for before in (b"w1", None):
        of = coarse([single[before]])[0]
        p = [10 ** model.log_probabilities(np.array([of, coarse([single[t]])[0]]), np.array([0.0, coarse([pair[before, t]])[0]]), np.array([0, 2]), of)[1] for t in vocab]
        assert 0.8 < sum(p) < 1.25
