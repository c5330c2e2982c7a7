import hashlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gridpress.llm import piece_codec
from gridpress.llm.queries import piece_model_path

sentencepiece = pytest.importorskip("sentencepiece")
MODEL = piece_codec.PieceModel(open(piece_model_path(), "rb").read())
LIBRARY = sentencepiece.SentencePieceProcessor(model_file=piece_model_path())


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.one_of(st.sampled_from(" \n\t▁aéth.漢😀\0"), st.characters(blacklist_categories=["Cs"])), max_size=60))
def test_same_as_library(text):
    want = LIBRARY.encode(text)
    assert MODEL.encode(text, end=False) == want
    assert MODEL.decode(want) == LIBRARY.decode(want)
    spans = MODEL.encode_spans(text)
    assert [i for i, _, _ in spans] == want
    raw = text.encode()
    assert all(0 <= a <= b <= len(raw) for _, a, b in spans)
    edges = [(a, b) for k, (_, a, b) in enumerate(spans) if k == 0 or spans[k - 1][1:] != (a, b)]
    assert b"".join(raw[a:b] for a, b in edges) == raw


def test_long_part_equals_short_merges():
    text = "unbelievablyinterconnected" * 40
    assert MODEL.encode(text, end=False) == LIBRARY.encode(text)


def test_character_map_takes_the_longest_prefix():
    assert piece_codec.CharacterMap(b"").longest(b"abc", 0) is None


def test_documents(spark, messy):
    rows = {(r.doc_id, r.n_tokens, r.ids_sha256) for r in piece_codec.encode_documents(messy, piece_model_path()).collect()}
    empty = hashlib.sha256(b"2").hexdigest()
    assert (2, 1, empty) in rows and (3, 1, empty) in rows
    assert piece_codec.encode_documents(messy.limit(0), piece_model_path()).count() == 0


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.one_of(st.sampled_from(" \n\t▁aéth.漢😀\0"), st.characters(blacklist_categories=["Cs"])), max_size=60))
def test_spans_of_parts_equal_those_of_the_whole_text(text):
    assert list(map(tuple, MODEL.spans(MODEL.parts(text)).tolist())) == [(a, b) for _, a, b in MODEL.encode_spans(text)]


def test_documents_offer_spans(spark, messy):
    got = piece_codec.encode_documents(messy, piece_model_path(), with_ids=True, with_spans=True).collect()
    texts = {r.doc_id: r.text or "" for r in messy.collect()}
    assert any(r.span_start for r in got)
    for r in got:
        want = MODEL.encode_spans(texts[r.doc_id])
        assert list(zip(r.ids, r.span_start, r.span_end)) == want and r.ids[-1] == MODEL.end_id
        assert r.spans_sha256 == hashlib.sha256(b"".join(x.to_bytes(4, "little") for _, a, b in want for x in (a, b))).hexdigest()


def test_whole_table_equals_the_library(spark):
    """ids and decoded text of every document of a table, as the library gives them; spans cover each text's bytes."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = {r.doc_id: r for r in piece_codec.encode_documents(docs, piece_model_path(), with_spans=True).collect()}
    rows = docs.select("doc_id", "text").collect()
    assert len(got) == len(rows)
    for doc_id, text in rows:
        ids, r = [*LIBRARY.encode(text or ""), LIBRARY.eos_id()], got[doc_id]
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(LIBRARY.decode(ids).encode()).hexdigest()
        assert not r.span_end or (r.span_start[0] == 0 and r.span_end[-1] == len((text or "").encode()) and all(a <= b for a, b in zip(r.span_start, r.span_end, strict=True)))


@settings(max_examples=100, deadline=None)
@given(st.lists(st.text(alphabet="abcdefgh etaoinsr.ing", max_size=90), max_size=30))
def test_parts_merged_side_by_side_equal_the_heap(texts):
    MODEL.memo.clear()
    MODEL.learn([w for t in texts for w in MODEL.words(t)])
    for t in texts:
        assert MODEL.encode(t, end=False) == [i for p in MODEL.merge(MODEL.normalise(t)[0]) for i in MODEL.piece_ids(p)]
