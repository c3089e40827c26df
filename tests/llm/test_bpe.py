import hashlib
import struct

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from recordlink.llm import bpe

tokenizers = pytest.importorskip("tokenizers")


@pytest.fixture(scope="module")
def library():
    t = tokenizers.Tokenizer.from_file(bpe.default_path())
    t.no_padding()
    t.no_truncation()
    return t


OWN = bpe.load(bpe.default_path())


@settings(max_examples=400, deadline=None)
@given(st.text(st.one_of(st.characters(codec="utf-8", max_codepoint=0x2FF), st.sampled_from(list("abcdeß'sştİΣςé̸́ \n<|>endoftx日本語　")), st.characters(codec="utf-8", max_codepoint=0xFFFF, categories=["L", "N", "P", "Z"])), max_size=40))
def test_same_ids_as_the_library(text):
    t = tokenizers.Tokenizer.from_file(bpe.default_path()) if not hasattr(test_same_ids_as_the_library, "t") else test_same_ids_as_the_library.t
    test_same_ids_as_the_library.t = t
    want = t.encode(text, add_special_tokens=False).ids
    assert OWN.encode(text) == want
    assert OWN.decode(want) == t.decode(want, skip_special_tokens=False)


def test_every_document(docs, library):
    rows = {r["doc_id"]: r for r in bpe.encode_documents(docs).collect()}
    for d in docs.collect():
        ids = library.encode(d["text"] or "", add_special_tokens=False).ids
        r = rows[d["doc_id"]]
        assert r["token_ids"] == ids and r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_odd_rows(odd, none, library):
    got = bpe.encode_documents(odd, id_cols=("doc_id", "text", "n_words"))
    assert got.count() == odd.count()
    for r in got.collect():
        assert r["token_ids"] == library.encode(r["text"] or "", add_special_tokens=False).ids
    assert bpe.encode_documents(none).count() == 0
    assert {r["decoded"] for r in bpe.decode_ids(got.where("doc_id = 4")).collect()} == {library.decode(library.encode("One two three\nOne two three\nfour", add_special_tokens=False).ids)}
