import hashlib
import random

import numpy as np
import public_tokenizers
import pytest
import sentencepiece

from jointsem.llm import pieces
from jointsem.llm.pieces import Encoder, Model, round_trip

PATH = public_tokenizers.path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def library():
    return sentencepiece.SentencePieceProcessor(model_file=PATH)


def texts():
    rng = random.Random(9)
    odd = ["", " ", "  a  b ", "\n", "\x00a", "▁a ▁", "\t\t", "a​b", "ﬁ Ａ", "<s>x</s>", "<0x41>", "é", "�", "　a", "😀 x😀😀", "日本語" * 300, "a" * 3000, " " * 700, "ab" * 600, "x" + " " * 17 + "y"]
    vocab = ["hello", "world", "Straße", "ñandú", "the", "of", "ing", "42", "foo_bar", "https://x.y/z?a=b", "…", "🙂", "don't"]
    mixed = ["".join(rng.choice(vocab) + rng.choice([" ", "", "  ", "\n", ","]) for _ in range(rng.randrange(80))) for _ in range(60)]
    noise = ["".join(chr(rng.choice([rng.randrange(32, 127), rng.randrange(160, 900), rng.randrange(0x4E00, 0x4F00)])) for _ in range(rng.randrange(400))) for _ in range(60)]
    return odd + mixed + noise


def test_ids_equal_the_library(library):
    encoder = Encoder(Model(open(PATH, "rb").read()))
    every = texts()
    for part in (every, every[::-1], ["", ""], every[3:4]):
        ids, first = encoder.encode([t.encode() for t in part])
        plain, cut = encoder.model.decode(ids, first)
        for i, t in enumerate(part):
            want = library.encode(t)
            assert ids[first[i] : first[i + 1]].tolist() == want, t[:50]
            assert plain.tobytes()[cut[i] : cut[i + 1]].decode() == library.decode(want)


def test_round_trip(documents, library):
    rows = [*enumerate(texts()), (900, None), (None, "null id"), (0, "")]
    got = sorted((str(r[0]), *r[1:]) for r in round_trip(documents(rows), PATH).collect())
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = []
    for i, t in rows:
        ids = library.encode(t or "")
        want.append((str(i), len(ids), sha(",".join(map(str, ids))), sha(library.decode(ids))))
    assert got == sorted(want)
    assert round_trip(documents([]), PATH).collect() == []
    assert [r.ids for r in round_trip(documents([(1, "a b")]), PATH, ids_out=True).collect()] == [library.encode("a b")]


def test_words_that_share_a_hash_are_told_apart(library, monkeypatch):
    """With a hash of two values nearly all words share one."""
    monkeypatch.setattr(pieces, "_word_keys", lambda data, start, end: (end - start).astype(np.uint64) % np.uint64(2))
    encoder = Encoder(Model(open(PATH, "rb").read()))
    for part in (["ab cd", "ef"], ["xy zzz"], texts()[:40], ["one"], ["two"]):
        ids, first = encoder.encode([t.encode() for t in part])
        assert [ids[a:b].tolist() for a, b in zip(first[:-1], first[1:], strict=True)] == [library.encode(t) for t in part]
