"""Ids of packed documents against the tokenizer with its default setting."""

import random
import zlib

import numpy as np

from optjoin.llm import packing


def test_added_tokens_in_texts(spark):
    from tokenizers import Tokenizer

    import public_tokenizers

    coder = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    draw = random.Random(4)
    bits = ["<|endoftext|>", "<|endoftext|", "|>", " ", "  ", "\n", "a", " b", "it's", "é", "\u3000", "😀", "12"]
    texts = ["a <|endoftext|> b", "<|endoftext|><|endoftext|>", "x <|endoftext", *("".join(draw.choices(bits, k=12)) for _ in range(300))]
    own = packing.public_byte_bpe()
    want = [np.array(coder.encode(t, add_special_tokens=False).ids, "<u4") for t in texts]
    assert [own.encode(t).tolist() for t in texts] == [x.tolist() for x in want]
    assert own.encode(texts[0]).tolist() == [64, 220, 50256, 275]
    got = {r.doc_id: (r.doc_tokens, r.ids_crc32) for r in packing.pack(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), open_windows=500).collect()}
    assert got == {i: (len(x) + 1, zlib.crc32(np.append(x, np.uint32(1)).astype("<u4"))) for i, x in enumerate(want)}
