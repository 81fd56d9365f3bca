import re
import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tiersort.llm import repeats as r
from tiersort.llm.queries import QUERIES
from helpers import DATA


def plain(docs, length=50):
    """(id, bytes) rows -> sorted (id, n_bytes, n_removed, n_spans, sha)."""
    first = {}
    for i, t in docs:
        for k in range(len(t) - length + 1):
            s = t[k:k + length]
            if s not in first or i < first[s]:
                first[s] = i
    out = []
    for i, t in docs:
        hit = bytearray(len(t))
        for k in range(len(t) - length + 1):
            if first[t[k:k + length]] < i:
                hit[k:k + length] = b"\x01" * length
        kept = bytes(c for c, h in zip(t, hit) if not h)
        spans = sum(h and (k == 0 or not hit[k - 1]) for k, h in enumerate(hit))
        out.append((i, len(t), sum(hit), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def got(df):
    return sorted(tuple(x) for x in r.digest(df).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect())


def test_query_matches_brute_force(spark):
    docs = [(x.doc_id, x.text.encode()) for x in spark.read.parquet(f"{DATA}/documents.parquet").collect()]
    rows = sorted(tuple(x) for x in QUERIES["op3_repeats"](spark, DATA).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect())
    assert rows == plain(docs)
    assert any(x[2] for x in rows)


def repetitive(seed):
    rng = random.Random(seed)
    parts = ["".join(rng.choice("abé ") for _ in range(rng.randrange(20, 120))) for _ in range(12)]
    return ["".join(rng.choice(parts)[rng.randrange(20):] + rng.choice(["", "x", "\n"]) for _ in range(rng.randrange(9))) for _ in range(80)]


@pytest.mark.parametrize("hot, shard_bytes", [(20_000, 8 << 20), (3, 1500)])
def test_repetitive_rows(spark, hot, shard_bytes):
    texts = repetitive(3)
    rows = [(i // 2 * 3 - 20, t) for i, t in enumerate(texts)] + [(7, None), (8, ""), (9, "a" * 400), (10, "a" * 30), (11, "ab" * 300), (200, "a" * 49), (200, texts[3]), (200, texts[3])]
    df = spark.createDataFrame([(i, t, "q") for i, t in rows], "doc_id long, text string, id string").repartition(5)
    assert got(r.repeated(df, hot=hot, shard_bytes=shard_bytes)) == plain([(i, (t or "").encode()) for i, t in rows])


def test_long_texts_go_in_parts(spark, monkeypatch):
    monkeypatch.setattr(r, "CHUNK", 700)
    rng = random.Random(4)
    passage = "".join(rng.choice("abcdefg ") for _ in range(900))
    rows = [(i, "".join(rng.choice("ab ") for _ in range(rng.randrange(3000))) + passage[rng.randrange(300):] + "x" * rng.randrange(90)) for i in range(12)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert got(r.repeated(df, shard_bytes=4000)) == plain([(i, t.encode()) for i, t in rows])


def test_passage_of_every_document_is_one_entry_a_home(spark):
    rows = [(i, f"page {i} " + "the same notice stands below every page of this site and of all others " * 2) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert got(r.repeated(df, hot=50)) == plain([(i, t.encode()) for i, t in rows])


def test_rows_without_id_and_empty_table(spark):
    df = spark.createDataFrame([(None, "z" * 100), (1, "z" * 100), (2, "z" * 100)], "doc_id long, text string")
    assert [(x.id, len(x.spans)) for x in r.repeated(df).orderBy("id").collect()] == [(None, 0), (1, 0), (2, 1)]
    assert r.repeated(df.limit(0)).count() == 0


def test_kept_text(spark):
    df = spark.createDataFrame([(1, "start " + "m" * 60), (2, "other:" + "m" * 60 + " end")], "doc_id long, text string")
    out = {x.id: (bytes(x.kept), [(s.a, s.b) for s in x.spans]) for x in r.repeated(df, with_text=True).collect()}
    assert out == {1: (b"start " + b"m" * 60, []), 2: (b"other: end", [(6, 66)])}


def test_every_window_has_one_anchor():
    rng = np.random.default_rng(5)
    texts = [bytes(rng.integers(97, 100, n).astype(np.uint8)) for n in (0, 49, 50, 51, 700, 3)] + [b"ab" * 200]
    seen = {}
    for who, first, n, off, h in r._snippets(texts, 50):
        for w, f, k, o, x in zip(who, first, n, off, h):
            for j in range(k):
                assert (w, f + j) not in seen
                seen[w, f + j] = (texts[w][f + o:f + o + r.GRAM], o - j, x)
    assert len(seen) == sum(max(0, len(t) - 49) for t in texts)
    by_string = {}
    for (w, f), (gram, off, x) in seen.items():
        assert 0 <= off <= 26
        assert by_string.setdefault(texts[w][f:f + 50], (gram, off, x)) == (gram, off, x)


def test_matching_statistics_against_scan():
    rng = random.Random(2)
    pieces = ["".join(rng.choice("ab") for _ in range(rng.randrange(5, 40))).encode() for _ in range(15)]
    index = r.RunLengthIndex(pieces, np.arange(15), 6)
    patterns = ["".join(rng.choice("abc") for _ in range(rng.randrange(1, 30))).encode() for _ in range(25)] + pieces
    length, rows, places = index.statistics(patterns)
    at = 0
    for p in patterns:
        for i in range(len(p)):
            want = max((k for k in range(len(p) - i + 1) if any(p[i:i + k] in x for x in pieces)))
            assert length[at] == want, (p, i)
            place = places[at]
            assert bytes((index.text[place:place + want] - 2).astype(np.uint8)) == p[i:i + want]
            if want >= 6:
                assert index.smallest(rows[at:at + 1])[0] == min(k for k, x in enumerate(pieces) if p[i:i + 6] in x)
            at += 1


def test_pack_round_trip():
    for x in ([], [0], [1, 2 ** 63, 5], list(range(1000))):
        a, b = r._unpack(r._pack(np.array(x, np.uint64), np.array([7])))
        assert a.tolist() == x and b.tolist() == [7]


def test_staged_steps_leave_no_shuffle_files(spark):
    import time

    from tiersort.llm.common import CLEANUP, staged

    # as a string: the names of the local files of the session's block manager
    held = lambda: {x for x in re.findall(r"shuffle_[0-9_]+\.\w+", spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager().getAllFiles().mkString(" "))}
    before = held()
    rows = spark.range(1000).groupBy((F.col("id") % 7).alias("k")).agg(F.count("*").alias("n"))
    out = staged(rows, "few")
    for _ in range(50):
        if not held() - before:
            break
        time.sleep(0.1)
    assert not held() - before
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, rows.collect())) and spark.conf.get(CLEANUP) == "false"
    assert held() - before  # those of a plain query stay
