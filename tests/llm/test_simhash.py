import itertools
import random
import re

import xxhash

from jointsem.llm.simhash import fingerprints, links, near_duplicates


def plain_fingerprint(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    grams = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(rows):
    fps = [(i, plain_fingerprint(t)) for i, t in rows]
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(range(len(fps)), 2):
        if (fps[a][1] ^ fps[b][1]).bit_count() <= 2:
            root[find(a)] = find(b)
    least = {}
    for n, (i, _) in enumerate(fps):
        r = find(n)
        least[r] = min((x for x in (least.get(r), i) if x is not None), default=None)
    return sorted(((i if i is not None else -1), f, least[find(n)]) for n, (i, f) in enumerate(fps))


def test_matches_brute_force(documents):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(60)]
    rows = []
    for i in range(120):
        t = [rng.choice(words) for _ in range(rng.randrange(0, 120))]
        rows.append((i, " ".join(t)))
        rows += [(1000 + 10 * i + k, " ".join([*t[: len(t) - k], "Zed"])) for k in range(rng.randrange(3))]
    rows += [(5000, None), (5001, ""), (5002, " \t\n"), (5003, "one"), (5004, "ONE"), (5004, "ONE"), (None, "one"), (5005, "x " * 30000)]
    got = sorted(((r.doc_id if r.doc_id is not None else -1), r.fp % 2**64, r.component_id) for r in near_duplicates(documents(rows)).collect())
    assert got == plain_components(rows)


def test_empty_table(documents):
    assert near_duplicates(documents([])).collect() == []


def test_trie_join_finds_every_link(spark):
    rng = random.Random(5)
    base = [rng.getrandbits(64) for _ in range(40)]
    fps = {b ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(4))) for b in base for _ in range(12)} | {0, 2**64 - 1}
    fps = sorted(fps)
    df = spark.createDataFrame([(f - 2**64 if f >> 63 else f,) for f in fps], "fp long")
    for leaf in (4, 100, 10**6):
        root = {f: f for f in fps}

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for u, v in links(df, 2, leaf).collect():
            assert ((u ^ v) % 2**64).bit_count() <= 64
            root[find(u % 2**64)] = find(v % 2**64)
        want = {f: f for f in fps}

        def whole(x):
            while want[x] != x:
                x = want[x]
            return x

        for a, b in itertools.combinations(fps, 2):
            if (a ^ b).bit_count() <= 2:
                want[whole(a)] = whole(b)
        pairs = {(find(f), whole(f)) for f in fps}
        assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})


def test_fingerprints_of_short_texts(documents):
    got = {r.id: r.fp % 2**64 for r in fingerprints(documents([(1, "Ab"), (2, "a b"), (3, None)])).collect()}
    assert got == {1: plain_fingerprint("Ab"), 2: plain_fingerprint("a b"), 3: 0}
