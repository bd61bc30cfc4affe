import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sharetree.llm.registry import tokenizer_path
from sharetree.llm.storage import scratch_path
from sharetree.llm.token_store import Segment, encode_segment, encoder, read_documents, token_at, token_documents, write_token_store
from tests.llm.conftest import ODD_ROWS


@given(st.lists(st.integers(0, 2**32 - 1) | st.integers(0, 300), max_size=3000))
@settings(max_examples=60, deadline=None)
def test_codes_round_trip_and_random_access(ids):
    segment = Segment(encode_segment(np.array(ids, np.uint32)))
    assert segment.slice(0, len(ids)).tolist() == ids
    for i in range(0, len(ids), 97):
        assert segment.token(i) == ids[i]
        assert segment.slice(i, min(i + 50, len(ids))).tolist() == ids[i : i + 50]


@given(st.lists(st.text(alphabet=st.sampled_from(list("ab. \n\t'sé1 \x1c\x85") + ["\U0001f600"]), max_size=40), max_size=8))
@settings(max_examples=200, deadline=None)
def test_cut_encoding_equals_whole_encoding(texts):
    e = encoder(tokenizer_path())
    assert [x.tolist() for x in e(texts)] == [x.ids for x in e.tokenizer.encode_batch(texts, add_special_tokens=False)]


def brute(rows):
    t, at, out = encoder(tokenizer_path()).tokenizer, 0, []
    for doc_id, text in rows:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        out.append((doc_id, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    return out


def test_documents_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    got = sorted(map(tuple, token_documents(docs, tokenizer_path()).select("doc_id", "start", "n_tokens", "ids_crc32").collect()))
    assert got == brute(sorted((r.doc_id, r.text) for r in docs.collect()))


def test_odd_rows_and_empty_table(spark, odd):
    got = [tuple(r) for r in token_documents(odd, tokenizer_path()).orderBy("start").collect()]
    assert [r[0] for r in got] == sorted((r[0] for r in ODD_ROWS), key=lambda x: (x is not None, x))
    assert got[0][1] == 0 and all(a[1] + a[2] == b[1] for a, b in zip(got, got[1:]))
    assert token_documents(odd.limit(0), tokenizer_path()).count() == 0


def test_single_token_by_position(spark, odd):
    path = scratch_path(spark, "store-test")
    write_token_store(odd, path, tokenizer_path())
    rows = read_documents(spark, path).orderBy("start").collect()
    last = rows[-1]
    assert token_at(spark, path, last.start + last.n_tokens - 1) == 2
    assert token_at(spark, path, last.start + last.n_tokens) is None


def test_bad_magic():
    with pytest.raises(ValueError):
        Segment(b"XXXX" + bytes(20))
