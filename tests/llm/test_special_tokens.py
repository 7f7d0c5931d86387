"""Special tokens inside texts keep their ids."""

from __future__ import annotations

import zlib

import numpy as np
from tissuemap.llm import packing
from tokenizers import Tokenizer

from .test_operators import PATH, corpus


def test_pieces_equal_the_unmodified_tokenizer(spark):
    t = Tokenizer.from_file(PATH)
    texts = [r[1] or "" for r in corpus()]
    texts += ["x <|endoftext|> plain", "<|endoftext|>", "a<|endoftext|><|endoftext|>b", "  <|endoftext|>\n\n<|endoftext|> ", "<|endoftext |> <|ENDOFTEXT|>", "l'<|endoftext|>'ll"]
    want = [[*e.ids, 2] for e in t.encode_batch(texts, add_special_tokens=False)]
    assert any(50256 in ids for ids in want)
    got = packing.pieces(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), PATH, 64).collect()
    assert sum(r["length"] for r in got) == sum(map(len, want))
    for r in got:
        part = want[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"]
