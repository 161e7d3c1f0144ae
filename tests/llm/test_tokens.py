import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from keyhop.llm import bpe
from keyhop.llm.packing import Plan, pack
from keyhop.llm.token_counts import token_counts

PATH = public_tokenizers.path("word_bpe_49k.json")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def test_cache_equals_library_on_random_strings(library):
    rng = random.Random(1)
    pool = [chr(i) for i in range(256)] + list("''''   aaessttrrvvemlld") + ["<|endoftext|>", "<|", "Σ", "İ", "é", " "]
    lengths, ids = bpe.Lengths(PATH, bpe.frequent_lengths(PATH, ["the", "tion,", "a1b2", "don't"]), limit=500), bpe.Ids(PATH, limit=500)
    for i in range(6000):
        s = "".join(rng.choice(pool) for _ in range(rng.randint(0, 12)))
        s = "".join(c for c in s if ord(c) < 256) if i % 2 else s
        want = library.encode(s, add_special_tokens=False).ids
        assert lengths.count(s) == len(want) and ids.encode(s) == bpe.little_endian(want)


def test_counts(docs, odd, texts, library):
    rows = {r["doc_id"]: r for r in token_counts(docs, PATH).collect()}
    for i, t in enumerate(texts):
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert (rows[i]["n_tokens"], rows[i]["n_bytes"], rows[i]["over_limit"]) == (n, len((t or "").encode()), n > 2048)
    assert token_counts(odd, PATH).count() == 4
    assert token_counts(odd.limit(0), PATH).count() == 0


def test_plan_places_every_piece():
    rng = np.random.default_rng(1)
    for _ in range(150):
        capacity = int(rng.integers(1, 60))
        counts = np.bincount(rng.integers(1, capacity + 1, int(rng.integers(0, 200))), minlength=capacity + 1)
        plan = Plan(counts, capacity)
        got = np.zeros_like(counts)
        for times, lengths in plan.groups:
            assert times > 0 and sum(lengths) <= capacity
            for x in lengths:
                got[x] += times
        assert (got == counts).all()
        assert plan.sequences >= -(-int((counts * np.arange(capacity + 1)).sum()) // capacity)


def test_exact_complements_first():
    counts = np.zeros(11, int)
    counts[[7, 3, 5, 2, 1, 4, 10]] = [2, 1, 2, 1, 1, 1, 3]
    plan = Plan(counts, 10)
    assert plan.sequences == 7  # 3 whole, 7+3, 7+2+1, 5+5, and the 4 alone


def test_packing_round_trip(docs, odd, texts, library):
    rows = pack(docs, PATH, capacity=64, with_ids=True).collect()
    by_doc = {}
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["piece"])):
        assert r["length"] == len(r["ids"]) // 4 <= 64 and r["ids_crc32"] == zlib.crc32(r["ids"])
        assert r["start"] == len(by_doc.get(r["doc_id"], b"")) // 4
        by_doc[r["doc_id"]] = by_doc.get(r["doc_id"], b"") + bytes(r["ids"])
    for i, t in enumerate(texts):
        assert by_doc[i] == bpe.little_endian([*library.encode(t or "", add_special_tokens=False).ids, 1])
    filled = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == filled.get(r["sequence_id"], 0)
        filled[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(filled.values()) <= 64 and len(filled) <= -(-sum(filled.values()) // 64) * 1.05 + 1
    assert pack(odd, PATH).count() == 4 and pack(odd.limit(0), PATH).count() == 0
