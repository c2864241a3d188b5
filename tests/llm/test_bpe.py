import hashlib
import struct

import pytest
from tokenizers import Tokenizer

from lattice_pages.llm import bpe
from lattice_pages.llm.queries import QUERIES, vocabulary

VOCAB = vocabulary("word_bpe_49k.json")
HARD = ["", "a", "It's <|endoftext|>ok<|startoftext|><|endoftext|>", "ΣΑΣ Σ final ΑΣ İstanbul", "é x​y \x1c a\x1db \x85 　z", "don't we'll 'S 'RE 123 4٣ ½ ²", "x" * 3000, "ab" * 700 + "!?" * 400, "😀😀 ퟿ 日本語テキスト", "<|ENDOFTEXT|> <|end", "ͅẞ ẞ ǅ ﬁ", "à̧́ ᄀ각", "line\n\n\ttab\r\nend  "]


@pytest.mark.parametrize("text", HARD)
def test_equals_the_library(text):
    lib, own = Tokenizer.from_file(VOCAB), bpe.WordBpe(VOCAB)
    ids = lib.encode(text, add_special_tokens=False).ids
    assert own.encode(text) == ids and own.encode_text(text)[1] == own.decode(ids) == lib.decode(ids, skip_special_tokens=False)


def test_long_words_equal_short_ones():
    own = bpe.WordBpe(VOCAB)
    for word in ("internationalisation", "abababababab", "zzzzzzzz", "tionthereer"):
        ids = [own.vocab[c] for c in word[:-1]] + [own.vocab[word[-1] + own.end]]
        assert bpe.merge_short(ids, own.merges) == bpe.merge_long(ids, own.merges)


def test_query(spark, sf):
    lib = Tokenizer.from_file(VOCAB)
    texts = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = {r.doc_id: r for r in QUERIES["op3_bpe_roundtrip"](spark, sf).collect()}
    assert set(got) == set(texts)
    for i, t in texts.items():
        ids = lib.encode(t, add_special_tokens=False).ids
        want = (len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest())
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == want


def test_odd_rows(spark):
    df = spark.createDataFrame([(1, None, 1), (1, None, 1), (None, "é ok", 2), (3, "word " * 60000, 3)], "doc_id long, text string, ids int")
    got = sorted((r.doc_id or 0, r.n_tokens) for r in bpe.encode_decode(df, VOCAB, keep_output=True).collect())
    assert got[1:] == [(1, 0), (1, 0), (3, 60000)] and bpe.encode_decode(df.limit(0), VOCAB).count() == 0
