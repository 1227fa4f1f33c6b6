import hashlib
import random
import re

import pytest

from jointsem.llm.contamination import hits, judged


def words(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def plain(docs, bench):
    out = []
    for i, t in docs:
        w = words(t)
        hit, items = set(), set()
        for item, b in bench:
            v = words(b)
            n = min(13, len(v))
            for k in range(len(v) - n + 1 if n else 0):
                for at in range(len(w) - n + 1):
                    if w[at : at + n] == v[k : k + n]:
                        hit |= set(range(at, at + n))
                        items.add("" if item is None else str(item))
        out.append((i, len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


@pytest.fixture
def tables(spark, documents):
    rng = random.Random(7)
    vocab = [f"v{i}" for i in range(30)] + ["Été", "日本", "x" * 40]
    say = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    bench = [(k, say(n)) for k, n in enumerate([40, 13, 14, 25, 12, 5, 1, 300])] + [(20, "same " * 40), (21, "same " * 14), (22, ""), (23, None), (None, say(20)), (30, "a, b. c! d? e f g h i j k l m n")]
    docs = []
    for i in range(60):
        parts = [say(rng.randrange(60)) for _ in range(3)]
        src = words(rng.choice(bench)[1] or "")
        a = rng.randrange(max(1, len(src)))
        parts.insert(rng.randrange(4), "; ".join(src[a : a + rng.choice([11, 12, 13, 14, 30])]))
        docs.append((i, " ".join(parts)))
    docs += [(100, None), (101, ""), (102, "Same-" * 200), (103, bench[0][1].upper()), (103, bench[0][1].upper()), (None, bench[3][1]), (104, bench[7][1] + " tail " * 3000), (105, "x")]
    return docs, bench, documents(docs), spark.createDataFrame(bench, "item_id long, text string")


@pytest.mark.parametrize(("block", "sieve"), [(1 << 20, 1 << 20), (300, 1 << 20), (1 << 20, 0)])
def test_matches_brute_force(tables, block, sieve):
    docs, bench, d, b = tables
    got = judged(hits(d, b, block_bytes=block, sieve=sieve)).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated").collect()
    assert sorted((tuple(r) for r in got), key=str) == plain(docs, bench)


def test_carry_returns_the_columns(tables):
    docs, _, d, b = tables
    got = hits(d, b, carry=True)
    assert set(d.columns) < set(got.columns)
    assert sorted((str(r.doc_id), r.text or "") for r in got.collect()) == sorted((str(i), t or "") for i, t in docs)


def test_columns_with_the_names_of_results_are_replaced(tables):
    _, _, d, b = tables
    got = hits(d.selectExpr("*", "'x' as n_words", "'y' as starts", "'z' as print", "'w' as block", "'v' as _1"), b, carry=True)
    row = got.where("doc_id = 105").first()
    assert (row.n_words, row.starts, row.print, row.block, row._1) == (1, [], "z", "w", "v")


def test_empty_tables(spark, documents):
    none = spark.createDataFrame([], "item_id long, text string")
    assert judged(hits(documents([]), none)).collect() == []
    assert [r.n_hit for r in judged(hits(documents([(1, "a b")]), none)).collect()] == [0]
