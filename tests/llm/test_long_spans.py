"""Texts with very long spans, or with more distinct pieces than the piece table holds."""

from __future__ import annotations

import random

import numpy as np
import pytest
from tokenizers import Tokenizer

from vecblock.llm import token_files
from vecblock.llm.entries import vocabulary

PATH = vocabulary("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def long_texts():
    rng = random.Random(3)
    chinese = "".join(chr(rng.randint(0x4E00, 0x9FA5)) for _ in range(40_000))
    letters = "a" * 600_000
    return ["short one", chinese, "", f"before {letters} after", f"{chinese} x {letters}12{letters}\n\nend", "it's " + "b'" * 3000, "x" + " " * 5000 + "y", "last " + "c" * 2000]


def check(enc, texts):
    tok = Tokenizer.from_file(PATH)
    got = enc.encode([t.encode() for t in texts])
    assert [np.frombuffer(g, enc.type).tolist() for g in got] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


def test_long_spans(long_texts):
    assert len(Tokenizer.from_file(PATH).encode(long_texts[1], add_special_tokens=False).ids) > 0xFFFF
    check(token_files.Encoder(PATH), long_texts)


def test_more_pieces_than_slots():
    enc = token_files.Encoder(PATH)
    enc.table = token_files.PieceTable(enc.type, 1 << 8)
    rng = random.Random(4)
    texts = [" ".join("".join(rng.choice("abcdef") for _ in range(6)) for _ in range(n)) for n in (50, 2000, 60, 100, 90)]
    enc.encode([texts[0].encode()])
    with_limit = [enc.encode([t.encode()]) for t in texts]
    assert enc.table.slots == 1 << 8
    check(token_files.Encoder(PATH), texts)
    assert with_limit == [token_files.Encoder(PATH).encode([t.encode()]) for t in texts]


def test_file_with_long_spans(spark, long_texts):
    from vecblock.llm.shared import shared_root

    tok = Tokenizer.from_file(PATH)
    docs = spark.createDataFrame(list(enumerate(long_texts)), "doc_id long, text string")
    path = f"{shared_root(spark)}/tokens-long"
    token_files.write_token_file(docs, PATH, path, parts=2)
    back = {r.doc_id: np.frombuffer(r.ids, np.uint32).tolist() for r in token_files.read_token_file(spark, path, with_ids=True).collect()}
    assert back == {k: [*tok.encode(t, add_special_tokens=False).ids, 0] for k, t in enumerate(long_texts)}
