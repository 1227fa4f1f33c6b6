import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from jointsem.llm.toxicity import Kernel, Units, fit, plain_similarity, score_documents, similarity

CLEAN = "the river ran past the old mill and the fields were green in spring"


def say(rng, *extra):
    words = CLEAN.split()
    rng.shuffle(words)
    for w in extra:
        words.insert(rng.randrange(len(words)), w)
    return " ".join(words) + "."


@pytest.mark.parametrize("pair", [("idiot", "i.d.i.o.t"), ("idiot", "idxiot"), ("moron", "oron"), ("Straße", "strasse"), ("ab", "ab"), ("", "x"), ("banana", "bandana")])
def test_kernel_equals_enumeration(pair):
    assert similarity(*pair) == pytest.approx(plain_similarity(*pair))


def test_inserted_characters_stay_similar():
    assert similarity("idiot", "i-d-i.o.t") == pytest.approx(1) and similarity("idiot", "idiiot") > 0.8 > similarity("idiot", "edition")


def test_bound_loses_no_unit():
    rng = random.Random(2)
    kernel = Kernel([b"worthless", b"idiot"])
    texts = ["".join(rng.choice("idotwrhles. ") for _ in range(200)).encode() for _ in range(30)] + [b"idiot worthles", b"i d i o t"]
    units = Units(texts)
    found = dict(zip(*(x.tolist() for x in kernel.similar(units)), strict=True))
    for k in range(len(units.size)):
        want = [plain_similarity(units.spelled(k).decode(), m.decode()) for m in kernel.landmarks]
        want = [w if w >= 0.75 else 0 for w in want]
        assert found.get(k, [0, 0]) == pytest.approx(want)


def test_held_out_texts(spark, documents):
    rng = random.Random(4)
    insults = ["dunderhead", "nincompoop", "blockhead"]
    rows = [(i, say(rng, rng.choice(insults)) if i % 4 == 0 else say(rng)) for i in range(200)]
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(200)] + [(None, 1), (7, None)], "doc_id long, toxic int")
    rows += [(1000, say(rng, "nin.com.poop")), (1001, say(rng, "b l o c k h e a d")), (1002, None), (1003, ""), (1004, (CLEAN + " ") * 3000 + "dunderheead"), (None, say(rng)), (1005, CLEAN), (1005, CLEAN)]
    got = score_documents(documents(rows), labels).collect()
    assert len(got) == len(rows)
    of = {r.doc_id: r for r in got}
    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    assert all(of[i].predicted == int(i % 4 == 0) for i in range(200))
    assert [of[i].predicted for i in (1000, 1001, 1002, 1003, 1004, 1005, None)] == [1, 1, 0, 0, 1, 0, 0]
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)


def test_without_labels(spark, documents):
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert [r.score for r in score_documents(documents([(1, "a")]), none).collect()] == [pytest.approx(0.5)]
    assert score_documents(documents([]), none).collect() == []


def test_fit_with_one_class():
    assert fit([b"a", b"b"], np.array([0, 0])).scores([b"a"])[0] < 0.5


def test_kindred_units_are_pooled():
    """No one word tells, and clean texts hold such words now and then; their share tells, in any script."""
    rng = random.Random(6)
    ends = ["".join(rng.choice("abdeiklmnorstu") for _ in range(rng.randint(2, 7))) for _ in range(300)]

    def text(kind):
        n = rng.randint(60, 200)
        words = [rng.choice(ends) for _ in range(n)]
        for k in range(max(2, n // 25) if kind else rng.random() < 0.3):
            words[k * 7] = kind + rng.choice(ends) if kind else rng.choice(["achl", "réê"]) + rng.choice(ends)
        return " ".join(words).encode()

    make = lambda n: ([text(["achl", "réê", "", "", "", ""][i % 6]) for i in range(n)], np.array([int(i % 6 < 2) for i in range(n)]))
    (train, y), (held, want) = make(900), make(300)
    got = fit(train, y).scores(held) >= 0.5
    assert (got == want).mean() > 0.95 and got[want == 1].mean() > 0.9


def test_scores_equal_a_plain_evaluation():
    """Sentence by sentence, with every kernel value enumerated."""
    rng = random.Random(8)
    insults = ["dunderhead", "nincompoop", "blockhead"]
    train = [(say(rng, rng.choice(insults)) + " " + say(rng) if i % 3 == 0 else say(rng)).encode() for i in range(90)]
    scorer = fit(train, np.array([int(i % 3 == 0) for i in range(90)]))
    assert scorer.kernel.landmarks and scorer.openings is None
    texts = [say(rng, "dunder.head") + " " + say(rng), say(rng, "blockheads", "nincompoops"), say(rng), "", "b l o c k h e a d! the mill", "block head"]
    for t in texts:
        margin = scorer.offset
        for sentence in re.split(r"(?<=[.!?;:])\s+", t):
            words = sentence.lower().split()
            units = [*words, *("".join(run) for single, run in itertools.groupby(words, lambda w: len(w) == 1 and "a" <= w <= "z") if single for run in [list(run)] if len(run) >= 3)]
            near = [max([k for w in units if (k := plain_similarity(w, m.decode())) >= 0.75] or [0.0]) for m in scorer.kernel.landmarks]
            margin = max(margin, float(np.dot(near, scorer.weight)) + scorer.offset)
        assert scorer.scores([t.encode()])[0] == pytest.approx(1 / (1 + math.exp(-(scorer.slope * margin + scorer.level))), abs=1e-9), t


def test_held_out_recall_in_every_language(spark):
    """On the given tables: toxic texts are caught in all four languages, and clean ones left alone."""
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    found = score_documents(docs, labels).where("held_out").join(labels, "doc_id").join(docs.select("doc_id", "lang"), "doc_id")
    rows = {r.lang: r for r in found.groupBy("lang").agg(*[F.sum(F.expr(f"int(toxic = {y} and predicted = {p})")).alias(n) for n, y, p in (("caught", 1, 1), ("missed", 1, 0), ("alarms", 0, 1), ("quiet", 0, 0))]).collect()}
    assert set(rows) == {"de", "en", "es", "fr"}
    for r in rows.values():
        assert r.caught >= 0.8 * (r.caught + r.missed) and r.alarms <= 0.01 * (r.alarms + r.quiet)
