import random

import numpy as np

from tiersort.llm import decontaminate as d
from tiersort.llm.queries import op8_decontaminate
from helpers import DATA, plain_contamination


def result(df):
    return {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in df.collect()}


def test_wavelet_and_index_against_scan():
    rng = np.random.default_rng(1)
    seq = rng.integers(0, 5, 700).astype(np.int32)
    tree = d.WaveletMatrix(seq, 3)
    at = rng.integers(0, 701, 50)
    for c in range(5):
        assert tree.rank(np.full(50, c), at).tolist() == [int((seq[:i] == c).sum()) for i in at]
    seq = np.append(seq + 1, 0).astype(np.int32)
    index = d.FmIndex(seq, 6)
    table = np.array([[1, 2, 3], [0, 1, 1], [4, 4, 4], [0, 0, 2]], np.int32)
    low, high = index.search(table, np.array([3, 2, 3, 1]))
    for (a, b), w in zip(zip(low, high), ([1, 2, 3], [1, 1], [4, 4, 4], [2])):
        want = [i for i in range(700) if seq[i:i + len(w)].tolist() == w]
        assert sorted(index.locate(np.arange(a, b)).tolist()) == want


def test_query_matches_brute_force(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").collect()
    items = spark.read.parquet(f"{DATA}/benchmark.parquet").collect()
    want = plain_contamination([(r.doc_id, r.text) for r in docs], [(r.item_id, r.text) for r in items])
    assert result(op8_decontaminate(spark, DATA)) == want
    assert any(x[4] for x in want.values())


def fixture(spark):
    rng = random.Random(2)
    w = ["aa", "bb", "Cc", "ñandú", "x1"]
    mix = lambda n: " ".join(rng.choice(w) for _ in range(n))
    items = [(1, mix(14)), (2, mix(14)), (2, "aa bb"), (3, None), (4, " .,"), (5, "x1"), (6, mix(10))]
    docs = [(i, mix(rng.randrange(60)), "z") for i in range(60)] + [(60, None, "z"), (61, "", "z"), (62, ("Aa, " * 9 + items[0][1] + "\n") * 400, None), (62, "aa bb", "z")]
    return docs[:-1], items, spark.createDataFrame(docs[:-1], "doc_id long, text string, items string"), spark.createDataFrame(items, "item_id long, text string")


def test_edge_cases_and_blocks(spark):
    docs, items, df, bench = fixture(spark)
    want = plain_contamination([x[:2] for x in docs], items)
    for block in (8_000_000, 20):  # one block, and several with merged spans
        assert result(d.digest(d.contamination(df, bench, block_chars=block, shard_words=50))) == want
    assert d.contamination(df.limit(0), bench).count() == 0
    assert result(d.digest(d.contamination(df, bench.limit(0))))[0][1:3] == (0, 0)


def test_cut_leaves_no_phrase(spark):
    docs, items, df, bench = fixture(spark)
    left = d.cut(df, bench, least=10).collect()
    long_items = [(i, t) for i, t in items if t and len(t.split()) >= 10]
    again = plain_contamination([(r.doc_id, r.text) for r in left], long_items)
    assert not any(x[4] for x in again.values())
    before = plain_contamination([x[:2] for x in docs], long_items)
    kept = {r.doc_id: r.text for r in left}
    assert all(kept[i] == t for i, t, _ in docs if not before[i][4])


def test_many_blocks_keep_rows_apart(spark):
    docs = spark.createDataFrame([(1, "a b c d"), (1, "x y z"), (None, "a b"), (None, None), (2, "c d x y")], "doc_id long, text string")
    items = spark.createDataFrame([("p", "a b"), ("q", "c d x"), ("r", "x y")], "item_id string, text string")
    rows = lambda **o: sorted(((r.id, r.n_words, [tuple(s) for s in r.spans], r["items"]) for r in d.contamination(docs, items, **o).collect()), key=str)
    assert len(rows()) == 5 and rows(block_chars=1) == rows()
