"""Added tokens in the text get their own id, as from a fresh tokenizer."""

import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from driftclust.llm import packing, token_files, tokens
from driftclust.llm.scratch import lean

END = "<|endoftext|>"


def fresh():
    return Tokenizer.from_file(tokens.default_path())


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_encoder_equals_a_fresh_tokenizer():
    rng = random.Random(3)
    parts = ["a", "word", " ", "  ", "\n", "'s", "é", "<|", "|>", "endoftext", END, "<|endoftext", "1", "\x85"]
    texts = [None, "", END, f"a {END} b", f"a{END}b{END}", "a <|endof", "text|> b", f" {END} ", ("some words " * 200_000) + f"x {END} y " + "more words " * 200_000]
    texts += ["".join(rng.choice(parts) for _ in range(rng.randint(0, 30))) for _ in range(2000)]
    ids, off = tokens.encoder(tokens.default_path()).encode(pa.array(texts))
    for i, enc in enumerate(fresh().encode_batch([t or "" for t in texts], add_special_tokens=False)):
        assert ids[off[i] : off[i + 1]].tolist() == enc.ids
    assert ids[off[3] : off[4]].tolist() == [64, 220, 50256, 275]


def test_token_files_and_packing_with_added_tokens(spark):
    texts = ["first text", f"a {END} b", "next one", None, f"{END}{END}"]
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    lib, start, want = fresh(), 0, []
    for i, t in enumerate(texts):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 0]
        want.append((i, start, len(ids), crc(ids)))
        start += len(ids)
    assert sorted(tuple(r) for r in token_files.round_trip(df).collect()) == want
    got = {r.doc_id: (r.length, r.ids_crc32) for r in packing.pack_documents(df).collect()}
    for i, t in enumerate(texts):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 2]
        assert got[i] == (len(ids), crc(ids))


def test_lean_passes_batches_on_and_errors_up():
    assert list(lean(lambda rows: (2 * r for r in rows))([1, 2])) == [2, 4]

    def broken(rows):
        yield next(rows)
        raise ValueError("broken")

    got = lean(broken)(iter([1]))
    assert next(got) == 1
    with pytest.raises(ValueError, match="broken"):
        next(got)
