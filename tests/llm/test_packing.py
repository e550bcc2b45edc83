import random
import zlib
from collections import defaultdict

import numpy as np
from tokenizers import Tokenizer

from windowforge.llm.bpe import vocabulary
from windowforge.llm.packing import combinations, ids_of, least_squares, pack, solve


def test_combinations_fill_the_window():
    found = combinations(np.arange(1, 64), 64)
    assert (found.sum(axis=1) == 64).all() and len({tuple(x) for x in found}) == len(found)
    assert len(found) == sum(1 for a in range(1, 64) for b in range(a, 64) if a + b == 64) + sum(1 for a in range(1, 64) for b in range(a, 64) for c in range(b, 64) if a + b + c == 64)


def test_least_squares_finds_an_exact_mix():
    combos = combinations(np.arange(1, 16), 16)
    h = np.zeros(17)
    for c, n in ((3, 500.0), (9, 300.0)):
        for x in combos[c][combos[c] > 0]:
            h[x] += n
    x = least_squares(combos, h, 5000)
    got = sum(np.bincount(combos[:, k], weights=x, minlength=17) for k in range(3))
    assert np.abs(got[1:] - h[1:]).max() < 1


def test_plan_places_every_remainder_once():
    rng = random.Random(3)
    for trial in range(20):
        h = np.zeros(65, dtype=np.int64)
        for _ in range(rng.randint(0, 300)):
            h[rng.choice([5, 9, 59, 32, 64 - 9, rng.randint(1, 63)])] += rng.randint(1, 4)
        plan, filled = solve(h, 64), defaultdict(list)
        for r in range(1, 64):
            for k in range(h[r]):
                pieces = plan.place(r, k)
                assert sum(p[1] for p in pieces) == r
                for _, n, s, o in pieces:
                    filled[s].append((o, n))
        total = int((h * np.arange(65)).sum())
        for spans in filled.values():
            at = 0
            for o, n in sorted(spans):
                assert o == at
                at += n
            assert at <= 64
        assert len(filled) == -(-total // 64)


def test_pack_rows(spark):
    rng = random.Random(5)
    texts = [None, "", "a <|endoftext|> b", "word " * 3000] + ["".join(rng.choice("the of abc \n") for _ in range(rng.randint(0, 9000))) for _ in range(60)]
    rows = [(i, t, "x") for i, t in enumerate(texts)] + [(7, texts[7], "x"), (None, "no id", "x")]
    got = pack(spark.createDataFrame(rows, "doc_id long, text string, start string")).collect()
    lib = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    by_doc, by_sequence = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        by_sequence[r.sequence_id].append(r)
    copies = defaultdict(int)
    for i, t, _ in rows:
        copies[i] += 1
    for i, t, _ in rows:
        ids = np.array([*lib.encode(t or "", add_special_tokens=False).ids, 0], dtype="<u4")
        assert sum(r.length for r in by_doc[i]) == copies[i] * len(ids)
        for r in by_doc[i]:
            assert r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes())
    full = 0
    for pieces in by_sequence.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        full += at == 1024
        assert at <= 1024
    assert full >= len(by_sequence) - 1


def test_empty_table(spark):
    assert pack(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_ids_are_the_librarys():
    lib = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    for t in ("", "a<|endoftext|><|endoftext|>  b", "é" * 500, "  \n\n x", "I'm they'LL 123 ４５"):
        assert ids_of(vocabulary("byte_bpe_50k.json"), t).tolist() == lib.encode(t, add_special_tokens=False).ids
