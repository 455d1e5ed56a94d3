"""Encodings against the library, best-sum segmentations against brute force, decoding round trips."""

import numpy as np
import public_tokenizers
import sentencepiece
from hypothesis import given, settings
from hypothesis import strategies as st

from deltahop.llm import sentence_pieces as sp

V = sp.load_vocabulary()
ENCODE = sp.SentencePieceEncoder(V, memo_size=2000, longest=40)
LIBRARY = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))


def encoded(encode, texts):
    raw = [(" " + t.replace("▁", " ")).encode() if t else b"" for t in texts]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    ids, bounds = encode(np.frombuffer(b"".join(raw), np.uint8), offsets)
    return [ids[bounds[k] : bounds[k + 1]].tolist() for k in range(len(texts))], ids, bounds


@settings(max_examples=400, deadline=None)
@given(st.lists(st.text(alphabet=st.sampled_from(list("aeinrstTho  \n.é漢字😀1▁ß\x00")), max_size=60), max_size=6))
def test_equals_the_library(texts):
    got, ids, bounds = encoded(ENCODE, texts)
    assert got == [LIBRARY.encode(t) for t in texts]
    text, at = sp.Decoder(V)(ids, bounds)
    for k, t in enumerate(texts):
        assert text[at[k] : at[k + 1]].tobytes().decode()[1:] == t.replace("▁", " ")


def test_real_words_equal_the_library(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    want = {r.doc_id: LIBRARY.encode(r.text or "") for r in docs.collect()}
    got = sp.encode_documents(docs, with_ids=True).collect()
    assert {r.doc_id: r.ids for r in got} == want and all(r.round_trip for r in got)


def test_best_sum_matches_brute_force():
    encode = sp.SentencePieceEncoder(V, relax=sp.relax_scores)
    ids = {V.pieces[i]: i for i in np.flatnonzero(V.usable)}
    for word in ["the", "there", "internationally", "xqz", "aaaa"]:
        raw = (" " + word).encode()
        best = [0.0] + [-np.inf] * len(raw)
        for j in range(1, len(raw) + 1):
            for i in range(j):
                if raw[i:j] in ids:
                    best[j] = max(best[j], best[i] + V.scores[ids[raw[i:j]]])
        (got,), _, _ = encoded(encode, [word])
        assert abs(V.scores[got].sum() - best[-1]) < 1e-6


def test_odd_rows(spark, odd_docs):
    got = sp.encode_documents(odd_docs).collect()
    assert len(got) == odd_docs.count() and all(r.round_trip for r in got)
    assert {r.n_tokens for r in got if r.doc_id in (2, 3)} == {0}
    assert sp.encode_documents(odd_docs.limit(0)).collect() == []
