import hashlib
import random

import numpy as np
import pytest

from walkrank.llm import bpe

P = pytest.importorskip("public_tokenizers")
PATH = P.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def reference():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(PATH)


def texts() -> list[str]:
    rng = random.Random(5)
    parts = [" ", "  ", "\n", "a", "the", "'s", "1", "é", "　", " ", "!", "<|endoftext|>", "\t", "日本", "\x85", "\x1d", "\U0001f600", "tion", "Zx"]
    out = ["", " ", "don't we'll  's  ", "a \n b", "x  \n  y", "<|endoftext|> <|endoftext|>", "=" * 300, "ab" * 500]
    out += ["".join(rng.choice(parts) for _ in range(rng.randint(1, 14))) for _ in range(1500)]
    return out + ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz ") for _ in range(rng.randint(1, 40))) for _ in range(800)]


def test_ids_and_text_are_those_of_the_library(reference):
    enc = bpe.encoder(PATH)
    for t, want in zip(texts(), reference.encode_batch(texts(), add_special_tokens=False)):
        assert enc.encode(t) == want.ids, t
        assert enc.decode(want.ids) == reference.decode(want.ids, skip_special_tokens=False)


def test_frame_with_nulls_repeats_and_clashing_columns(spark, reference):
    rows = [(1, "hello world", 9), (1, "hello world", 9), (2, None, 9), (None, "", 9), (3, "x" * 5000, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_tokens int")
    got = bpe.encode_frame(docs, PATH).collect()
    assert len(got) == 5 and set(got[0].asDict()) == {"doc_id", "text", "n_tokens", "ids_sha256", "decoded_sha256", "ids"}
    for r in got:
        ids = reference.encode(r.text or "", add_special_tokens=False).ids
        assert r.ids == ids and r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((r.text or "").encode()).hexdigest()
    back = bpe.decode_frame(bpe.encode_frame(docs, PATH), PATH).select("text", "decoded").collect()
    assert all((t or "") == d for t, d in back)
    assert bpe.encode_frame(docs.limit(0), PATH, digests_only=True).count() == 0
