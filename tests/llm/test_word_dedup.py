import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from jointsem.llm.recompression import Names, compress
from jointsem.llm.text import Words, space_table
from jointsem.llm.word_dedup import WordScheme, dedup_words


def plain(rows, width=35):
    words = [re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode()) for _, t in rows]
    n = Counter(tuple(w[k : k + width]) for w in words for k in range(len(w) - width + 1))
    out = []
    for (i, _), w in zip(rows, words, strict=True):
        gone = set()
        for k in range(len(w) - width + 1):
            if n[tuple(w[k : k + width])] > 1:
                gone |= set(range(k, k + width))
        kept = b" ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((str(i), len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def cases():
    rng = random.Random(17)
    vocab = [f"w{i}" for i in range(25)] + ["é", "x" * 70]
    say = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    shared = [say(n) for n in (30, 36, 50, 90)]
    rows = [(i, say(rng.randrange(40)) + rng.choice([" ", "\n"]) + rng.choice(shared) + "\t" + say(rng.randrange(30)) + " " + rng.choice(shared)) for i in range(60)]
    rows += [(100 + i, rows[2][1]) for i in range(8)] + [(7, rows[7][1]), (None, rows[9][1]), (None, say(80))]
    rows += [(200, None), (201, ""), (202, "a " * 34), (203, "a " * 35), (204, "a " * 36 + "b"), (205, "a b " * 60), (206, "c " + "a " * 100 + "d"), (207, "a b a a b b " * 30), (208, say(5000))]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("hot", [4096, 3])
def test_matches_brute_force(documents, monkeypatch, hot):
    from jointsem.llm import repeats

    monkeypatch.setattr(repeats, "_HOT_LEAST", hot)
    rows = cases()
    got = dedup_words(documents(rows).repartition(5)).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()
    assert sorted((str(r[0]), *r[1:]) for r in got) == plain(rows)


@pytest.mark.parametrize("bits", [3, 8])
def test_words_and_symbols_that_share_a_hash_get_names_of_their_own(documents, bits):
    """With names of so few bits nearly all definitions share one, and only further names tell them apart."""
    rows = cases()[:45]
    got = dedup_words(documents(rows).repartition(3), bits=bits).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()
    assert sorted((str(r[0]), *r[1:]) for r in got) == plain(rows)


def test_equal_names_stand_for_equal_words():
    """A symbol's exact name decides: altering it alone makes two equal windows differ."""
    scheme = WordScheme(20)
    passage = " ".join(f"w{i}" for i in range(80))
    texts = [passage.encode(), f"x {passage} y".encode()]
    s = scheme.scan(texts)
    at = np.flatnonzero(np.isin(s.h, s.h[s.doc == 0]) & (s.symbol >= 0))
    assert len(at) > 2
    zero = np.zeros(len(at), np.int64)

    def classes():
        _, size, content = s.pieces(at, zero, s.count[at])
        return scheme.classes(content, np.cumsum(size) - size, s.count[at])

    before = classes()
    assert len(set(before.tolist())) < len(before)
    s.symbols.exact = s.symbols.exact.copy()
    s.symbols.exact[s.symbol[at[s.doc[at] == 0]]] += np.uint64(1)
    assert len(set(classes().tolist())) > len(set(before.tolist()))


def test_columns_with_the_names_of_results_are_replaced(documents):
    docs = documents([(1, "a b c")]).selectExpr("*", "'x' as n_words", "'y' as copies", "'z' as _id", "'w' as _starts")
    got = dedup_words(docs).first()
    assert (got.n_words, got.copies, got._id, got._starts) == (3, "y", "z", "w")


def test_empty_table(documents):
    assert dedup_words(documents([])).collect() == []


def test_symbols_fixed_inside_a_passage_recur_with_it():
    rng = random.Random(3)
    passage = [rng.choice("abcde") for _ in range(60)]
    texts = [" ".join([rng.choice("abcde") for _ in range(rng.randrange(30))] + passage + [rng.choice("abcde") for _ in range(20)]).encode() for _ in range(20)]
    words = Words(texts, space_table())
    codes = words.hashes()
    x, _ = compress(codes, codes, words.doc, words.first, Names(), rounds=3)
    seen = []
    for d, t in enumerate(texts):
        p = words.first[d] + next(k for k in range(100) if t.split()[k : k + 60] == [c.encode() for c in passage])
        m = (x.low >= p) & (x.high <= p + 60) & (x.doc == d)
        seen.append({(int(a), int(b) - p, int(c) - p) for a, b, c in zip(x.name[m], x.low[m], x.high[m], strict=True)})
    assert len(set.intersection(*seen)) == len(seen[0]) == len(set.union(*seen)) > 5
    assert np.all(np.diff(x.low) >= 0) and np.all(np.diff(x.high) >= 0)
