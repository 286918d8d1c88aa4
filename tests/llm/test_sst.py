import io
import zlib

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from setanon.llm import sst
from setanon.llm.encoding import PieceEncoder

BYTE, WORD = (public_tokenizers.path(f) for f in ("byte_bpe_50k.json", "word_bpe_49k.json"))
T = {p: Tokenizer.from_file(p) for p in (BYTE, WORD)}
E = {BYTE: PieceEncoder(BYTE, spaced=True, memo_limit=500), WORD: PieceEncoder(WORD, spaced=False, memo_limit=500)}


WORDS = ["the", "thin,", "Élan", "été.", "it's", "x-ray", "AB!!", "de%%%", "<|endoftext|>", "a1b2", "ß", "\u0130x", "e\u0301", "\u4e2d\u6587", "", "\t", "\r", "'s", "\u2003", "\x1c", "end.'t", "\U0001f600", "\u03a3\u03c3"]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=40), st.lists(st.tuples(st.sampled_from(WORDS), st.sampled_from([" ", "\n", "  ", "\n\n", "", " \n"])), max_size=12).map(lambda x: "".join(a + b for a, b in x))), max_size=6))
def test_encoder_equals_library(texts):
    for p in (BYTE, WORD):
        got = [np.frombuffer(b, "<u4").tolist() for b in E[p].encode(texts)]
        assert got == [T[p].encode(t, add_special_tokens=False).ids for t in texts]


def test_encoder_equals_library_on_given_texts():
    import pyarrow.parquet as pq

    texts = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"]).column(0).to_pylist()[:400]
    test_encoder_equals_library.hypothesis.inner_test(texts)


def test_round_trip_and_lookup():
    buf = io.BytesIO()
    w = sst.Writer(buf, id_bytes=2, block_bytes=200)
    rows = [(None, [7])] + [(i * 3 - 50, list(range(i % 9))) for i in range(400)]
    for k, v in rows:
        w.add(sst.key_of(k), np.asarray(v, "<u2").tobytes())
    w.close()
    r = sst.Reader(buf)
    assert [(sst.id_of(k), np.frombuffer(v, "<u2").tolist()) for k, v in r.scan()] == rows
    for k, v in rows:
        assert r.get(k).tolist() == v
    assert all(r.get(i * 3 - 49) is None for i in range(-5, 420))
    assert len(r.where) > 5


def test_query_matches_direct(spark, tmp_path):
    rows = [(5, "two words"), (1, None), (3, ""), (None, "x"), (3, "again"), (9, "long " * 3000)]
    df = spark.createDataFrame([(a, b, 1) for a, b in rows], "doc_id long, text string, start int")
    made = sst.write_shards(df, str(tmp_path / "s"), tokenizer=BYTE)
    made = spark.createDataFrame(made.collect(), made.schema)
    got = [tuple(r)[:4] for r in sst.read_shards(spark, made).orderBy("start").collect()]
    want, at = [], 0
    for k, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "")):
        ids = T[BYTE].encode(t or "", add_special_tokens=False).ids + [0]
        want.append((k, at, len(ids), zlib.crc32(np.asarray(ids, "<u4").tobytes())))
        at += len(ids)
    assert got == want


def test_empty_table(spark, tmp_path):
    df = spark.createDataFrame([], "doc_id long, text string")
    made = sst.write_shards(df, str(tmp_path / "e"), tokenizer=BYTE)
    assert sst.read_shards(spark, made).count() == 0


def test_damage_is_noticed():
    buf = io.BytesIO()
    w = sst.Writer(buf, id_bytes=2)
    w.add(sst.key_of(1), b"\1\0")
    w.close()
    raw = bytearray(buf.getvalue())
    raw[3] ^= 1
    with pytest.raises(Exception):
        list(sst.Reader(io.BytesIO(bytes(raw))).scan())


def test_texts_of_a_batch_are_encoded_together():
    """Ids of whole batches, line starts and odd texts included, are those of the library text by text."""
    import numpy as np
    import public_tokenizers
    from tokenizers import Tokenizer

    from setanon.llm.encoding import PieceEncoder

    path = public_tokenizers.path("byte_bpe_50k.json")
    whole = Tokenizer.from_file(path)
    texts = ["the cat, the dog.\nthe cat!", "", "\ttab\r\nline", " lead", "a  b", "don't (stop)\nDon't", "Été à l'école\nété", "x<|endoftext|>y", "日本 語\n日本", "one", "éte é", "a1 b2, ...\n--", "the cat, the dog.\nthe cat!", "...", "ªº x", "a\tb", "0 1 0\n0"]
    enc = PieceEncoder(path, spaced=True)
    for _ in range(2):  # and from the memo
        flat, sizes = enc.closed(texts, 0)
        want = [whole.encode(t, add_special_tokens=False).ids + [0] for t in texts]
        assert sizes.tolist() == [len(w) for w in want]
        assert flat.tolist() == [i for w in want for i in w]
    assert [len(x) for x in enc.closed([], 0)] == [0, 0]
    assert enc.closed(["", ""], 0)[0].tolist() == [0, 0] and isinstance(flat, np.ndarray)
