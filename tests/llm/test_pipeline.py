import hashlib
import math
import random

import public_tokenizers
import pytest
import sentencepiece
from test_contamination import plain as plain_hits
from test_quality import plain_rules
from test_simhash import plain_components

import corpus_pipeline
from jointsem.llm.quality import BUCKETS, PRIOR, THRESHOLD

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def fixture():
    rng = random.Random(21)
    vocab = [f"word{i}" for i in range(300)]
    say = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    passage, item = say(70), say(40)
    rows = [(i, say(60 + i % 50) + "\n" + say(20)) for i in range(60)]
    rows += [(100 + i, " ".join(f"{rng.choice(vocab[:40])}$$$" for _ in range(80))) for i in range(15)]
    rows += [(200 + i, rows[i][1]) for i in range(5)] + [(300 + i, rows[i][1] + " tail") for i in range(5)]
    rows += [(400 + i, say(40) + " " + passage + " " + say(40)) for i in range(6)] + [(500 + i, say(60) + " " + item) for i in range(4)]
    rows += [(600, None), (601, ""), (602, "short text"), (603, "again and again " * 60), (604, "日本語 " * 60 + say(80)), (None, say(90)), (7, rows[7][1])]
    bench = [(1, item), (2, None), (3, say(20))]
    labels = [(i, int(i < 100), 0) for i, _ in rows if i is not None and i % 2 == 0 and i < 115] + [(None, 1, 0), (3, None, 0)]
    return rows, bench, labels


def plain_quality(spark, rows, labels):
    trusted = {i for i, q, _ in labels if q == 1 and i is not None}
    words = {i: (t or "").split() for i, (_, t) in enumerate(rows)}
    texts = sorted({w for ws in words.values() for w in ws})
    one = {r.w: r.h for r in spark.createDataFrame([(w,) for w in texts], "w string").selectExpr("w", "xxhash64(w) h").collect()}
    ends = sorted({(one[a], one[b]) for ws in words.values() for a, b in zip(ws[:-1], ws[1:], strict=False)})
    two = {(r.a, r.b): r.h for r in spark.createDataFrame(ends, "a long, b long").selectExpr("a", "b", "xxhash64(a, b) h").collect()}
    grams = {i: [one[w] % BUCKETS for w in ws] + [two[one[a], one[b]] % BUCKETS for a, b in zip(ws[:-1], ws[1:], strict=False)] for i, ws in words.items()}
    raw, good = {}, {}
    for n, (i, _) in enumerate(rows):
        for g in grams[n]:
            raw[g] = raw.get(g, 0) + 1
            good[g] = good.get(g, 0) + (i in trusted)
    ratio = {g: math.log((good[g] + PRIOR) / (raw[g] * sum(good.values()) / sum(raw.values()) + PRIOR)) for g in raw}
    return [r for n, r in enumerate(rows) if not plain_rules(r[1])[5] and sum(ratio[g] for g in grams[n]) / len(grams[n]) >= THRESHOLD]


def plain_bytes(rows, width=50):
    key = lambda i: 2**63 - 1 if i is None else i
    least = {}
    for i, t in rows:
        b = t.encode()
        for k in range(len(b) - width + 1):
            s = b[k : k + width]
            least[s] = min(least.get(s, key(i)), key(i))
    out = []
    for i, t in rows:
        b = t.encode()
        gone = set()
        for k in range(len(b) - width + 1):
            if least[b[k : k + width]] < key(i):
                gone |= set(range(k, k + width))
        left = bytes(x for k, x in enumerate(b) if k not in gone).decode(errors="ignore")
        if not gone or left:
            out.append((i, left))
    return out


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rows, bench, labels = fixture()
    at = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], SCHEMA).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    return at


def test_stages_match_brute_force(spark, folder, tmp_path):
    rows, bench, labels = fixture()
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    order = lambda x: sorted(x, key=str)
    want = plain_quality(spark, rows, labels)
    for n, (name, work) in enumerate(corpus_pipeline.STAGES[:-1]):
        out = work(spark, docs, folder)
        assert out.columns == docs.columns
        out.write.parquet(f"{tmp_path}/{n}")
        docs = spark.read.parquet(f"{tmp_path}/{n}")
        if n == 1:
            least = {(-1 if i is None else i): c for i, _, c in plain_components(want)}
            want = list(dict.fromkeys(r for r in want if least[-1 if r[0] is None else r[0]] == r[0]))
        elif n == 2:
            want = plain_bytes(want)
        elif n == 3:
            bad = {r[0] for r in plain_hits(want, bench) if r[5]}
            want = [r for r in want if r[0] not in bad]
        got = [(r.doc_id, r.text) for r in docs.collect()]
        assert order(got) == order(want), name
        assert all(r.n_chars == len(r.text) for r in docs.collect())
    assert 40 < len(want) < 80
    library = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    ids = {i: library.encode(t) for i, t in want}
    end = [(i, len(x), sha(",".join(map(str, x))), sha(library.decode(x))) for i, x in ids.items()]
    assert order(tuple(r) for r in corpus_pipeline.run(spark, folder).collect()) == order(end)


def test_empty_tables(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).collect() == []


def test_stages_pass_columns_through_whatever_their_names(spark, folder):
    clash = ["n_words", "n_bytes", "n_removed", "n_spans", "kept", "kept_sha256", "llr", "_kept_id", "_rows", "_own0", "copies", "id", "part", "fp", "starts", "items", "contaminated", "_id", "_th", "_1"]
    docs = spark.read.parquet(f"{folder}/documents.parquet").selectExpr("*", *[f"'{c}' as {c}" for c in clash])
    for name, work in corpus_pipeline.STAGES[:-1]:
        out = work(spark, docs, folder)
        assert out.columns == docs.columns, name
        row = out.where("doc_id = 20").first()
        assert all(row[c] == c for c in clash), name
    assert corpus_pipeline.STAGES[-1][1](spark, docs, folder).count() == docs.count()
