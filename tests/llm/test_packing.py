import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from setanon.llm import packing

PATH = public_tokenizers.path("word_bpe_49k.json")


def held(docs, pieces, window):
    """Every id once; windows gapless; only power-of-two windows are short."""
    cover, seqs = defaultdict(list), defaultdict(list)
    for d, s, k, q, o in pieces:
        cover[d].append((s, k))
        seqs[q].append((o, k))
    for d, x in enumerate(docs):
        at = 0
        for s, k in sorted(cover[d]):
            assert s == at and k > 0
            at += k
        assert at == len(x)
    for rows in seqs.values():
        at = 0
        for o, k in sorted(rows):
            assert o == at
            at += k
        assert at <= window and at & (at - 1) == 0


@settings(max_examples=80, deadline=None)
@given(st.lists(st.lists(st.integers(0, 30), min_size=1, max_size=90), max_size=30))
def test_shard_is_whole(lists):
    docs = [np.asarray(x, np.uint32) for x in lists]
    held(docs, packing.pack_shard(docs, 32), 32)


def test_scores_equal_plain_bm25():
    rnd = np.random.default_rng(1)
    docs = [rnd.integers(0, 40, rnd.integers(5, 60)).astype(np.uint32) for _ in range(25)]
    ix = packing.ShardIndex(docs, query_terms=1000)
    mean = np.mean([len(d) for d in docs])
    df = {t: sum(t in d for d in docs) for t in range(40)}
    for q in range(25):
        want = []
        for d in docs:
            s = 0
            for t in set(docs[q].tolist()):
                tf = int((d == t).sum())
                if df[t] > 1 and tf:
                    s += np.log1p((25 - df[t] + 0.5) / (df[t] + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len(d) / mean))
            want.append(s)
        assert np.allclose(ix.scores(q), want, atol=1e-3)


def test_neighbours_share_a_window():
    a, b = list(range(10, 26)), list(range(100, 116))
    docs = [np.asarray(x, np.uint32) for x in (a, b, a[::-1], b[::-1])]
    by = defaultdict(set)
    for d, _, _, q, _ in packing.pack_shard(docs, 32):
        by[q].add(d)
    assert sorted(map(sorted, by.values())) == [[0, 2], [1, 3]]


def test_query_is_whole(spark):
    rows = [(1, "alpha beta " * 900), (2, None), (None, "x"), (2, "again"), (5, "")]
    df = spark.createDataFrame([(a, b, 7) for a, b in rows], "doc_id long, text string, shard int")
    t = Tokenizer.from_file(PATH)
    got = defaultdict(list)
    for r in packing.pack(df, tokenizer=PATH).collect():
        got[(r.doc_id, r.doc_tokens)].append((r.start, r.length, r.ids_crc32))
    for k, x in rows:
        ids = t.encode(x or "", add_special_tokens=False).ids + [1]
        assert all(zlib.crc32(np.asarray(ids[s : s + n], "<u4").tobytes()) == c for s, n, c in got[(k, len(ids))])
        assert sum(n for _, n, _ in got[(k, len(ids))]) == len(ids)
    assert packing.pack(df.where("doc_id > 99"), tokenizer=PATH).count() == 0


def test_a_shard_scores_as_the_whole_corpus(spark):
    rnd = np.random.default_rng(2)
    docs = [(rnd.zipf(1.3, rnd.integers(20, 90)) % 50).astype("<u4") for _ in range(40)]
    tokens = spark.createDataFrame([(bytearray(d.tobytes()),) for d in docs], "ids binary").repartition(3)
    stats = packing.corpus_stats(tokens)
    assert stats.n == 40 and np.isclose(stats.mean, np.mean([len(d) for d in docs]))
    assert {t: c for t, c in enumerate(stats.df.tolist()) if c} == {t: c for t in range(50) if (c := sum(t in d for d in docs))}
    part, whole = packing.ShardIndex(docs[:15], stats=stats), packing.ShardIndex(docs)
    for q in range(15):
        got, want = part.scores(q), whole.scores(q)[:15]
        other = np.arange(15) != q
        assert np.allclose(got[other], want[other], atol=1e-3)


def test_all_terms_of_a_seed_are_asked():
    seed = np.arange(40, dtype=np.uint32)
    near = [np.asarray([t, 1000 + t], np.uint32) for t in range(40)]
    assert (packing.ShardIndex([seed, *near]).scores(0) > 0).all()


def test_texts_go_where_their_rarest_token_goes(spark):
    rnd = np.random.default_rng(5)
    docs = [np.append(rnd.integers(100, 160, 40), [t + 200, 1]).astype("<u4") for t in range(10) for _ in range(6)]
    docs += [docs[0], np.asarray([1], "<u4")]
    tokens = spark.createDataFrame([(i, bytearray(d.tobytes())) for i, d in enumerate(docs)], "doc_id long, ids binary")
    stats = packing.corpus_stats(tokens)
    at = {r.doc_id: r.shard for r in packing.dealt(tokens, stats, 2000).collect()}
    assert len(at) == len(docs) and len(set(at.values())) >= 5
    assert all(len({at[6 * t + k] for k in range(6)}) == 1 for t in range(10)) and at[60] == at[0]
    place = packing.by_rareness(stats.df)
    several = int((stats.df > 1).sum())
    for d in docs[:20]:
        own = sorted({(int(stats.df[x]), x) for x in d.tolist() if stats.df[x] > 1})[: packing.ROUTE]
        assert [int(np.flatnonzero(place == p)[0]) for p in packing.rarest(d, place, several)] == [x for _, x in own]


def test_a_hot_route_has_shards_of_its_own():
    assert packing.shard_plan([(1, 5), (2, 4), (3, 35), (4, 8), (5, 3)], 10) == {1: (0, 1), 2: (0, 1), 3: (1, 4), 4: (5, 1), 5: (6, 1)}
    assert packing.shard_plan([], 10) == {}


def test_ties_do_not_depend_on_the_order_of_rows(spark):
    rows = [(7, "alpha beta gamma " * 30), (7, "delta epsilon " * 40), (7, "alpha delta " * 20), (None, "zeta"), (None, "eta theta")]
    frame = lambda r: spark.createDataFrame(r, "doc_id long, text string")
    got = [sorted(map(str, packing.pack(frame(r), tokenizer=PATH, window=64).collect())) for r in (rows, rows[::-1])]
    assert got[0] == got[1]


def test_counts_of_documents_in_one_go():
    """Each token once for a document; routes' sizes are those of the dealing."""
    rnd = np.random.default_rng(2)
    docs = [rnd.integers(0, 9, n).astype("<u2") for n in (0, 1, 7, 30)]
    counts = packing._Counts()
    counts.add_all(np.concatenate(docs), [len(d) for d in docs])
    counts.add(docs[2])
    want = np.bincount(np.concatenate([np.unique(d) for d in [*docs, docs[2]]]), minlength=len(counts.df))
    assert counts.df.tolist() == want.tolist() and (counts.n, counts.total) == (5, 45)


def test_route_sizes_equal_the_dealing(spark):
    texts = ["tea pot", "tea kettle", "", None, "pot and kettle", "zebra"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(2)
    tokens = packing.encoded(packing.doc_text(docs), PATH, 1, "<u2").cache()
    counts = packing.corpus_stats(tokens)
    tokens = tokens.where("count IS NULL")
    by = {r.route: r["sum(size)"] for r in packing.routed(tokens, counts.df, "<u2").groupBy("route").sum("size").collect()}
    assert {r.route: r["size"] for r in packing.route_sizes(tokens, counts.df, "<u2").collect()} == by


def test_pieces_of_a_slice_are_looked_up_once():
    from setanon.llm.encoding import PieceEncoder

    texts = ["", "one two one", "Ünter über.\nDon't stop one", "a\tb  c", "x\n\ny 12", "<|endoftext|> z", "\n", "2 one", "東京 one", "one"]
    whole = Tokenizer.from_file(PATH)
    want = [[*whole.encode(t, add_special_tokens=False).ids, 1] for t in texts]
    enc = PieceEncoder(PATH, spaced=False)
    asked, make = [], enc.inner.make
    enc.inner.make = lambda piece: asked.append(piece) or make(piece)
    flat, sizes = enc.closed(texts, 1)
    assert sizes.tolist() == [len(x) for x in want]
    assert flat.tolist() == [i for x in want for i in x]
    assert asked.count("one") == 1
    assert [len(x) for x in enc.closed([], 1)] == [0, 0]
