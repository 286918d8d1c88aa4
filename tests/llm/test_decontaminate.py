import itertools
import random

import numpy as np

from setanon.llm import decontaminate as dc
from setanon.llm.words import WordHasher, windows


def test_word_hashes_separate_words():
    w = WordHasher()
    texts = ["The cat the CAT\x0bthe", "", "  ", "a\nb", "é É", "x" * 3000, "café"]
    h, at = w.texts([t.encode() for t in texts], block=64)
    assert np.diff(at).tolist() == [5, 0, 0, 2, 2, 1, 1]
    plain = [x for t in texts for x in t.encode().lower().split()]
    assert len(plain) == len(h)
    assert all((a == b) == (x == y) for (a, x), (b, y) in itertools.combinations(zip(h.tolist(), plain), 2))


def test_windows_follow_the_contract():
    w = WordHasher()
    texts = ["a b c d e f", "a b", "b a", "", "a b c d e", "b c d e f", "a b c d"]
    h, at = windows(*w.texts([t.encode() for t in texts]), 5)
    assert np.diff(at).tolist() == [2, 1, 1, 0, 1, 1, 1]
    by = [h[a:b].tolist() for a, b in zip(at, at[1:])]
    assert by[0] == by[4] + by[5] and by[1] != by[2] and len({x for y in by for x in y}) == 5


def test_masks_tolerate_substitutions():
    n = 14
    for bad in itertools.combinations(range(n), 2):
        ok = any(all((s + i) not in bad for i, c in enumerate(m) if c == "1") for m in dc.MASKS for s in range(n - len(m) + 1))
        assert ok, bad


def test_leaks_against_brute_force(spark):
    rnd = random.Random(5)
    vocab = [f"w{i}" for i in range(300)]
    items = [" ".join(rnd.choices(vocab, k=rnd.randint(14, 40))) for _ in range(12)] + ["tiny item", None]
    docs, want = [], set()
    for d in range(120):
        words = rnd.choices(vocab, k=rnd.randint(0, 80))
        if d % 3 == 0:
            i = rnd.randrange(12)
            part = items[i].split()
            for _ in range(len(part) // 10):
                part[rnd.randrange(len(part))] = "changed"
            at = rnd.randint(0, len(words))
            words[at:at] = [w.upper() + "," for w in part]
            want.add((d, i))
        docs.append((d, " ".join(words)))
    docs += [(500, None), (501, ""), (None, items[0])]
    df = spark.createDataFrame([(a, b, "z") for a, b in docs], "doc_id long, text string, item_id string")
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = dc.leaks(df, bench).collect()
    assert {(r.doc_id, r.item_id) for r in got} == want | {(None, 0)}
    small = dc.leaks(df, bench, dc.Options(block_items=5)).collect()
    assert sorted(map(tuple, small), key=str) == sorted(map(tuple, got), key=str)
    kept = dc.clean(df, bench)
    assert kept.columns == df.columns
    assert {r.doc_id for r in kept.collect()} == {d for d, _ in docs if d is not None} - {d for d, _ in want}
    assert dc.leaks(df, bench.limit(0)).count() == 0 and dc.leaks(df.limit(0), bench).count() == 0


def test_clean_texts_stay(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    bench = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet")
    text = {r.item_id: r.text for r in bench.collect()}
    bad = {r.doc_id for r in docs.collect() if any(t in r.text for t in text.values())}
    assert bad <= {r.doc_id for r in dc.leaks(docs, bench).collect()}


def test_spread_substitutions_do_not_hide_a_stretch():
    item = np.arange(47, dtype=np.uint64) + np.uint64(1)
    equal = np.arange(47) % 7 < 5
    assert dc.best_stretch(equal)[1] == 47 and equal.sum() < 0.75 * 47
    index = dc.SeedIndex([7], [" ".join(f"w{i}" for i in range(47))], dc.MASKS)
    text = " ".join(f"w{i}" if e else "changed" for i, e in enumerate(equal)).encode()
    (d, item, start, n, same), = dc.leaks_of([text], WordHasher(punctuation_is_space=True), index, dc.Options())
    assert (d, item) == (0, 0) and n >= 12 and same >= 0.75 * n


def test_accepted_finds_any_stretch():
    rnd = np.random.default_rng(3)
    for _ in range(400):
        equal = rnd.random(rnd.integers(1, 60)) < rnd.choice([0.5, 0.65, 0.72, 0.8])
        at = np.flatnonzero(equal)
        fit = [int(equal[a : b + 1].sum()) for a in at for b in at if b - a + 1 >= 12 and equal[a : b + 1].sum() >= 0.75 * (b - a + 1)]
        got = dc.accepted(equal, 12, 0.75)
        assert (got is None) == (not fit)
        if got:
            s, n, same = got
            assert n >= 12 and same == equal[s : s + n].sum() >= 0.75 * n


def made(seed, n=80):
    rnd = random.Random(seed)
    vocab = [f"w{i}" for i in range(60)]
    items = [" ".join(rnd.choices(vocab, k=rnd.randint(6, 40))) for _ in range(8)]
    items += [items[0], "tiny", "", None]
    docs = []
    for d in range(n):
        words = rnd.choices(vocab, k=rnd.randint(0, 60))
        for _ in range(rnd.randint(0, 2)):
            part = [w if rnd.random() < 0.85 else "changed" for w in (items[rnd.randrange(8)]).split()]
            at = rnd.randint(0, len(words))
            words[at:at] = part
        docs.append((d, " ".join(words)))
    return items, docs


def test_join_equals_one_process(spark):
    items, docs = made(6)
    docs += [(3, docs[3][1]), (None, None), (None, docs[5][1])]
    index, hasher = dc.SeedIndex(list(range(len(items))), [t or "" for t in items], dc.MASKS), WordHasher(punctuation_is_space=True)
    want = sorted((str(docs[d][0]), i, *v) for d, i, *v in dc.leaks_of([(t or "").encode() for _, t in docs], hasher, index, dc.Options()))
    df = spark.createDataFrame([(a, b, 1, 2, 3) for a, b in docs], "doc_id long, text string, h int, row_key int, salt int")
    bench = spark.createDataFrame([(i, t, "z") for i, t in enumerate(items)], "item_id long, text string, words string")
    assert want
    for opt in (dc.Options(), dc.Options(hot_seed=2, filter_bits=16, block_items=3)):
        assert sorted((str(r.doc_id), *tuple(r)[1:]) for r in dc.leaks(df, bench, opt).collect()) == want
    kept = dc.clean(df, bench)
    assert kept.columns == df.columns
    assert kept.count() == len(docs) - len({d for d, *_ in dc.leaks_of([(t or "").encode() for _, t in docs], hasher, index, dc.Options())})


def test_first_of_equal_stretches(spark):
    item = " ".join(f"a{i}" for i in range(14))
    df = spark.createDataFrame([(1, f"x {item} y {item} z"), (2, "pad " * 200_000 + item)], "doc_id long, text string")
    got = sorted(map(tuple, dc.leaks(df, spark.createDataFrame([(9, item)], "item_id long, text string")).collect()))
    assert got == [(1, 9, 1, 14, 14), (2, 9, 200_000, 14, 14)]


def test_a_hot_seed_is_dealt_over_salts(spark):
    mine = spark.createDataFrame([(7, k, 0) for k in range(1000)] + [(8, 0, 0)], "h long, row_key long, at int")
    seeds = spark.createDataFrame([(7, 1, 0), (8, 1, 3)], "h long, item long, pos int")
    dealt, spread = dc.salted(mine, seeds, dc.Options(hot_seed=100))
    share = [r["count"] for r in dealt.where("h = 7").groupBy("salt").count().collect()]
    assert len(share) == 10 and max(share) < 200
    assert dealt.join(spread, ["h", "salt"]).count() == 1001
