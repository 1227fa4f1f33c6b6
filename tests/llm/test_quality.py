import math
import random
import re
import struct
from collections import Counter

import pytest
import xxhash

from jointsem.llm.quality import BUCKETS, PRIOR, THRESHOLD, score, with_rules


def plain_rules(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    twice = {g for g, n in Counter(grams).items() if n > 1}
    inside = {i + k for i, g in enumerate(grams) if g in twice for k in range(3)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    failed = len(words) < 50 or 100 * len(inside) > 50 * len(words)
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(inside), failed


def texts():
    rng = random.Random(1)
    vocab = [f"wört{i}" for i in range(40)]
    out = [None, "", " \n\t ", "one", "a b c", "a b c a b c", "a a a a a", "x\n\nx\n x\nx", "é" * 70 + " #|<>", "\x0b\x0c a\rb"]
    out += [rng.choice([" ", "\n", " \t"]).join(rng.choice(vocab) for _ in range(rng.randrange(300))) for _ in range(60)]
    out += ["u v w x y " * 2000, " ".join(f"n{i % 700}" for i in range(5000))]
    return out


def test_rules_match_brute_force(documents):
    rows = list(enumerate(texts()))
    got = with_rules(documents([*rows, rows[-1]])).collect()
    assert len(got) == len(rows) + 1
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == plain_rules(rows[r.doc_id][1]), rows[r.doc_id][1]


def test_score_is_the_mean_log_ratio(spark, documents):
    good = "the cat sat on the mat and it was warm there. "
    rows = [(i, good * 2 + " ".join(f"w{i}x{k}" for k in range(60))) for i in range(8)] + [(100 + i, " ".join(f"z{k}$$$" for k in range(80))) for i in range(8)] + [(200, None)]
    labels = spark.createDataFrame([(i, 1) for i in range(8)] + [(100, 0), (None, 1), (3, None)], "doc_id long, quality int")
    got = {r.doc_id: r for r in score(documents(rows), labels).collect()}
    assert got[0].llr > got[100].llr and got[0].kept and not got[100].kept and got[200].llr is None
    assert not got[200].kept and got[100].llr < THRESHOLD


def test_without_labels_the_rules_decide(spark, documents):
    rows = [(1, " ".join(f"w{k}" for k in range(60))), (2, "short")]
    empty = spark.createDataFrame([], "doc_id long, quality int")
    got = {r.doc_id: (r.kept, r.llr) for r in score(documents(rows), empty).collect()}
    assert got == {1: (True, 0.0), 2: (False, 0.0)}
    assert score(documents([]), empty).collect() == []


def test_log_ratio_values(spark, documents):
    from jointsem.llm.quality import log_ratios

    rows = [(1, "a b"), (2, "a")]
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    got = sorted(r.ratio for r in log_ratios(documents(rows), labels, buckets=1 << 20).collect())
    share = lambda t, r: math.log((t + PRIOR) / (r * 3 / 4 + PRIOR))
    assert got == pytest.approx(sorted([share(1, 2), share(1, 1), share(1, 1)]))


def word_hash(w):
    return xxhash.xxh64_intdigest(w.encode(), 42)


def pair_hash(a, b):
    first = xxhash.xxh64_intdigest(struct.pack("<Q", word_hash(a)), 42)
    return xxhash.xxh64_intdigest(struct.pack("<Q", word_hash(b)), first)


def plain_score(rows, trusted):
    """llr and kept of every row, by counting in Python."""
    signed = lambda h: (h - 2**64 if h >= 2**63 else h) % BUCKETS
    grams = []
    for _, t in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        grams.append([signed(word_hash(w)) for w in words] + [signed(pair_hash(a, b)) for a, b in zip(words[:-1], words[1:], strict=False)])
    raw = Counter(g for gs in grams for g in gs)
    good = Counter(g for (i, _), gs in zip(rows, grams, strict=True) if i in trusted for g in gs)
    n, m = sum(raw.values()), sum(good.values())
    out = {}
    for (i, t), gs in zip(rows, grams, strict=True):
        llr = sum(math.log((good[g] + PRIOR) / (raw[g] * m / n + PRIOR)) for g in gs) / len(gs) if gs else None
        out[i] = (llr, bool(gs) and not plain_rules(t)[5] and llr >= THRESHOLD)
    return out


def test_llr_and_kept_match_brute_force(spark, documents):
    rng = random.Random(3)
    plain, junk = [f"w{i}" for i in range(30)], [f"j{i}" for i in range(30)]
    rows = list(enumerate(texts()))
    rows += [(1000 + i, " ".join(rng.choice(plain if rng.random() > i / 40 else junk) for _ in range(rng.randrange(40, 160)))) for i in range(40)]
    trusted = set(range(1000, 1012))
    labels = spark.createDataFrame([(i, 1) for i in trusted] + [(1039, 0), (None, 1)], "doc_id long, quality int")
    got = {r.doc_id: (r.llr, r.kept) for r in score(documents(rows), labels).collect()}
    want = plain_score(rows, trusted)
    assert {i: k for i, (_, k) in got.items()} == {i: k for i, (_, k) in want.items()}
    assert {k for _, k in want.values()} == {True, False}
    for i, (llr, _) in want.items():
        assert got[i][0] == (None if llr is None else pytest.approx(llr, abs=1e-9))


def test_columns_with_the_names_of_results_are_replaced(spark, documents):
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    docs = documents([(1, "a b c")])
    got = score(docs.selectExpr("*", "'x' as n_words", "'y' as kept", "1 as llr", "2 as _words", "3 as _text"), labels)
    assert got.columns.count("n_words") == got.columns.count("kept") == 1
    assert (got.first().n_words, got.first().kept) == (3, False)
    assert with_rules(docs.selectExpr("*", "'x' as n_words")).first().n_words == 3
