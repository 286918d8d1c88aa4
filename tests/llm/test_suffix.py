import hashlib
import random

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from setanon.llm import suffix as sx
from setanon.llm import suffix_order as so


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(1, 4), max_size=70))
def test_suffix_array(x):
    s = np.asarray(x, np.int64)
    assert sx.suffix_array(s).tolist() == sorted(range(len(x)), key=lambda i: x[i:])


def brute(texts, length):
    """Per text the removed byte positions."""
    seen = {}
    data = [(t or "").encode() for t in texts]
    for d, t in enumerate(data):
        for i in range(len(t) - length + 1):
            seen.setdefault(t[i : i + length], []).append((d, i))
    gone = [set() for _ in data]
    for where in seen.values():
        if len(where) > 1:
            for d, i in where:
                gone[d].update(range(i, i + length))
    out = []
    for t, g in zip(data, gone):
        runs = sum(i in g and i - 1 not in g for i in range(len(t)))
        out.append((len(t), len(g), runs, hashlib.sha256(bytes(c for i, c in enumerate(t) if i not in g)).hexdigest()))
    return out


def made(seed, unit):
    rnd = random.Random(seed)
    word = lambda: "".join(rnd.choices("abé ", k=rnd.randint(1, 5)))
    text = lambda n: "".join(word() for _ in range(n))
    out = [text(rnd.choice([0, 3, unit, 3 * unit])) for _ in range(25)]
    passage = text(unit)
    for _ in range(15):
        t = rnd.choice(out)
        cut = rnd.randint(0, len(t))
        out.append(rnd.choice([t, t[cut:] + "x", t[:cut] + "y" + t[cut:], text(5) + passage + text(5), t + t]))
    return out + [None, "", "z" * 700, passage, "é" * unit]


def test_query_equals_brute_force(spark):
    for seed, opt in ((1, sx.Options(length=40, gram=10, segment=90, sort_bytes=200)), (2, sx.Options(length=40, gram=9, bucket_contexts=2)), (3, sx.Options())):
        texts = made(seed, 20 if opt.length == 40 else 120)
        df = spark.createDataFrame([(i, i, t or "") for i, t in enumerate(texts)], "row_key long, doc_id long, text string")
        got = {r.doc_id: tuple(r)[1:] for r in sx.removed(df, opt).collect()}
        assert got == dict(enumerate(brute(texts, opt.length)))


def test_given_documents_and_repeated_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = docs.orderBy("doc_id").select("doc_id", "text").collect()
    got = {r.doc_id: tuple(r)[1:] for r in sx.op3_suffix(spark, "/root/testdata/sf0.001").collect()}
    assert got == dict(zip([r.doc_id for r in rows], brute([r.text for r in rows], 200)))
    from setanon.llm.common import keyed

    two = spark.createDataFrame([(1, "q" * 150 + "r" * 150), (1, "q" * 150 + "r" * 150), (None, "short")], "doc_id long, text string")
    assert sorted((r.n_bytes, r.n_removed, r.n_spans) for r in sx.removed(keyed(two)).collect()) == [(5, 0, 0), (300, 300, 1), (300, 300, 1)]
    assert sx.removed(keyed(two.limit(0))).count() == 0


def test_sort_by_all_tasks_equals_one_task(spark):
    rnd = random.Random(4)
    strings = [[rnd.randint(1, 3) for _ in range(rnd.choice([1, 2, 3, 7, 20, 41]))] for _ in range(60)]
    strings += [strings[0], [1] * 30, [1] * 29]
    df = spark.createDataFrame(list(enumerate(strings)), "t long, s array<long>")
    for one_task in (0,):
        got = sorted((r, strings[x.t][i:]) for x in so.suffix_ranks(df, 3, one_task).collect() for i, r in enumerate(x.r))
        assert [s for _, s in got] == sorted(s[i:] for s in strings for i in range(len(s)))


def test_hot_gram_is_sorted_by_all_tasks(spark):
    rnd = random.Random(9)
    passage = "".join(rnd.choices("abcd", k=60))
    texts = ["".join(rnd.choices("efgh", k=30)) + passage + "".join(rnd.choices("ijkl", k=30)) for _ in range(30)]
    texts += [texts[0][:70] + "m" + texts[1][70:], texts[2], "x" + passage[5:50], None, ""]
    df = spark.createDataFrame([(i, i, t or "") for i, t in enumerate(texts)], "row_key long, doc_id long, text string")
    for opt in (sx.Options(length=40, gram=10, bucket_contexts=3, one_task=2000),):
        assert {r.doc_id: tuple(r)[1:] for r in sx.removed(df, opt).collect()} == dict(enumerate(brute(texts, 40)))


def test_long_text_beside_short_ones_and_clashing_names(spark):
    rnd = random.Random(2)
    long = "".join(rnd.choices("abcdefgh ", k=900))
    texts = ["short", long, long[100:700] + "tail", "é" * 300, ""]
    df = spark.createDataFrame([(i, t, "g", 1, 2) for i, t in enumerate(texts)], "doc_id long, text string, gram string, s int, names int")
    from setanon.llm.common import keyed

    got = {r.doc_id: tuple(r)[1:] for r in sx.removed(keyed(df), sx.Options(segment=300)).collect()}
    assert got == dict(enumerate(brute(texts, 200)))
