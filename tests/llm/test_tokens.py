import hashlib
import random

import numpy as np
import pytest
from tokenizers import Tokenizer

from windowforge.llm.bpe import bpe_round_trip, encoder, vocabulary
from windowforge.llm.token_counts import count_by_chunks, model, spans_of, token_counts

TEXTS = [None, "", " ", "\n\n  \t", "a", "<|endoftext|>", "x<|endoftext|> y<|endoftext|>", "<s>a</s>", "é日本語 🤦🏽‍♂️", "=" * 3000, "a" * 5000, " " * 2000, "It's they'll 123 ４５ x▁y ▁ z", "0\x00b", "word " * 4000]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))


def test_encoder_is_the_librarys(library):
    bpe, rng = encoder(vocabulary("byte_bpe_50k.json")), random.Random(1)
    texts = [t for t in TEXTS if t] + ["".join(rng.choice(a) for _ in range(rng.randint(1, 80))) for a in ("abcdefgh ", "thein on", "ñéß ", "0123., ", "\n\t xX'", "aA!?", "日本語中文") for _ in range(200)]
    for t in texts:
        assert bpe.encode(t) == library.encode(t, add_special_tokens=False).ids, t
        assert bpe.decode(bpe.packed(t)) == library.decode(bpe.encode(t), skip_special_tokens=False)


def test_code_points_are_cut_alike(library):
    bpe = encoder(vocabulary("byte_bpe_50k.json"))
    points = [chr(c) for c in range(0, 0x30000, 7) if not 0xD800 <= c <= 0xDFFF]
    texts = [f"a{c}{c} {c}1{c}\n {c} b" for c in points]
    for t, e in zip(texts, library.encode_batch_fast(texts, add_special_tokens=False)):
        assert bpe.encode(t) == e.ids


def test_round_trip_rows(spark, library):
    rows = [(i, t, "clash") for i, t in enumerate(TEXTS)] + [(None, "x", "c"), (1, "", "c")]
    got = bpe_round_trip(spark.createDataFrame(rows, "doc_id long, text string, n_tokens string"), keep_ids=True).collect()
    assert len(got) == len(rows)
    texts = dict((i, t) for i, t, _ in rows)
    for r in got:
        ids = library.encode(texts[r.doc_id] or "", add_special_tokens=False).ids
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert r.decoded == (texts[r.doc_id] or "") and r.decoded_sha256 == hashlib.sha256(r.decoded.encode()).hexdigest()
    assert bpe_round_trip(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_spliced_counts():
    sp, rng = model(vocabulary("piece_bpe_32k.model")), random.Random(2)
    encode = lambda part, base: spans_of(sp, part, base)
    for alphabet in ("ab ", "the in on ", "ñé日本 \n", "aaaa", "   a", "x", "▁ a", "🤦日"):
        for _ in range(12):
            t = "".join(rng.choice(alphabet) for _ in range(rng.randint(300, 4000)))
            assert count_by_chunks(t, encode, 200, 16) == len(sp.encode(t)), (alphabet, len(t))


def test_count_rows(spark):
    sp = model(vocabulary("piece_bpe_32k.model"))
    rows = [(i, t, "c") for i, t in enumerate(TEXTS)] + [(0, None, "c")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, n_bytes string")
    for chunk in (262_144, 500):
        for r in token_counts(frame, chunk=chunk).collect():
            t = TEXTS[r.doc_id] or ""
            assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(t.encode()), len(sp.encode(t)), len(sp.encode(t)) > 4096)
    assert token_counts(spark.createDataFrame([], "doc_id long, text string")).count() == 0
