"""Texts that name an added token get the ids of the library as it comes."""

import struct
import zlib
from collections import Counter

import numpy as np
import pytest

from keyless.llm import entry, vocab

TEXTS = [
    "<|endoftext|>", "a <|endoftext|> b", "a  <|endoftext|>", "x<|endoftext|>y z", " <|endoftext|>\n <|endoftext|>  c d", "no such token here", "<|endoftext", "é <|endoftext|><|endoftext|> 中 e",
    " ".join(f"w{i}" for i in range(1500)) + " <|endoftext|> " + " ".join(f"v{i}" for i in range(1500)),
]


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(vocab.default_path(vocab.VOCAB))
    return lambda t: plain.encode(t, add_special_tokens=False).ids


def test_pieces_with_added_tokens(library):
    e = vocab.piece_encoder(vocab.default_path(vocab.VOCAB))
    rng = np.random.default_rng(7)
    alphabet = list("ab '\n\t  1!é") + ["don't", " <|endoftext|>", "<|endoftext|>", "<|endof"]
    texts = TEXTS + ["".join(alphabet[i] for i in rng.integers(0, len(alphabet), int(rng.integers(0, 14)))) for _ in range(2000)]
    for t, raw in zip(texts, e.encode(texts)):
        assert np.frombuffer(raw, e.dtype).tolist() == library(t), t


def test_packing_and_token_files_with_added_tokens(spark, tmp_path, library):
    spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string").repartition(2).write.parquet(f"{tmp_path}/documents.parquet")
    ids = [library(t) + [vocab.END_ID] for t in TEXTS]
    crc = lambda x: zlib.crc32(struct.pack(f"<{len(x)}I", *x))
    files = entry.queries()["op8_token_files"](spark, str(tmp_path)).orderBy("doc_id").collect()
    assert [(r["n_tokens"], r["ids_crc32"], r["start"]) for r in files] == [(len(x), crc(x), sum(map(len, ids[:d]))) for d, x in enumerate(ids)]
    want = Counter()
    for d, x in enumerate(ids):
        first = len(x) % 1024 or 1024
        for k, a in enumerate([0, *range(first, len(x), 1024)]):
            piece = x[a : first if k == 0 else a + 1024]
            want[d, k, a, len(piece), crc(piece)] += 1
    packed = entry.queries()["op6_pattern_packing"](spark, str(tmp_path)).collect()
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in packed) == want
